"""SentencePiece encoding by batched Viterbi, and decoding.

The vocabulary and scores are those of a model file; nothing is trained. A text gets a space in
front and is cut where a space follows something else, as no piece reaches across such a place
(checked when the model is loaded). Each distinct word of a batch is segmented once: words of equal
length stand in one matrix and advance together, substring hashes from running polynomial sums probe
the sorted piece keys, and for each end position the best sum of scores and its backpointer come from
vectorised maxima. Ties go to the longer last piece. A character that no piece covers is spelt in byte
pieces, at the lowest score less ten.

For a unigram model that is the segmentation with the greatest sum of scores. A file of merge ranks (BPE)
asks for the outcome of merging, best rank first. The same recurrence finds it on a smaller lattice: two
pieces may adjoin only where merging their joint text leaves just these two, and a text has exactly one
path of such pairs. Whether two pieces may adjoin follows from the ranks at which merging would have
made and joined their inner parts; it is worked out for whole arrays of pairs.

A word of any length takes this way: one longer than a window is cut into overlapping windows that stand in the
matrix like words, and paths are joined at a piece that two neighbours share, which keeps the path exact as
only one exists. Neighbours that share none (in text that repeats one character, say) are done again as one.
A unigram model's long words, and windows that have grown, are few: their pieces are probed at all places at once.

Decoding joins the pieces' bytes and takes the first space away, which restores every text exactly
(a literal U+2581 is spelt in bytes, for the pieces use it for spaces).

Cases: null and empty texts have no pieces and decode to empty ones; very long words without a space
give what a word-by-word recurrence would; null ids, repeated rows and further columns stay; an
empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from tidegraph.llm.common import give_back
from tidegraph.llm.ppm import KeyTable
from tidegraph.llm.textblocks import Block, blocks, mix64, powers

SPACE, MARK = 32, 0x2581
_BASE = np.uint64(0x9E3779B97F4A7C15)
#: Words of one length that advance together.
_ROWS = 1 << 15
_FILTER = 22
#: Places for pairs of pieces whose test is remembered, as a power of two.
_CACHE = 19
#: Bytes of text whose distinct words are segmented together; a worker takes some 150 bytes for each.
PIECE_BLOCK = 3 << 19


def _hash(points: np.ndarray) -> np.ndarray:
    return mix64(points.astype(np.uint64) + _BASE)


class PieceModel:
    """pieces: normal pieces with spaces for marks; scores; ids; bytes_: ids of the 256 byte pieces."""

    def __init__(self, pieces: list[str], scores: list[float], ids: list[int], bytes_: list[int], merges: bool = False):
        self.pieces, self.ids = pieces, np.array(ids, np.int32)
        self.scores = np.array(scores, float)
        self.bytes_ = np.array(bytes_, np.int32)
        # where merging decides, an unknown character stands only where no piece covers it
        self.unknown = -1e12 if merges else float(self.scores.min()) - 10.0
        self.longest = max(map(len, pieces))
        self.overlap = max(32, 2 * self.longest)
        self.window = 3 * self.overlap
        if any(" " in p.lstrip(" ") for p in pieces):
            raise ValueError("a piece holds a space after another character")
        keys = np.array([self._key(p) for p in pieces], np.uint64)
        order = np.argsort(keys)
        self.keys, self.rank = keys[order], order
        self.maybe = np.zeros(1 << _FILTER, bool)
        self.maybe[(keys >> np.uint64(64 - _FILTER)).astype(np.int64)] = True
        self.known: dict[int, bool] = {}
        self.cached_key, self.cached = np.full(1 << _CACHE, np.iinfo(np.uint64).max, np.uint64), np.zeros(1 << _CACHE, bool)
        self.by_text = {p: i for i, p in enumerate(pieces)}
        self.merges = merges
        if merges:
            self._learn_merges()
            self.scores = np.full(len(pieces), -1.0)  # one path is left, whatever its sum
        size = int(max(self.ids.max(), self.bytes_.max())) + 1
        spelt = [b""] * size
        for p, i in zip(pieces, ids, strict=True):
            spelt[i] = p.encode()
        for b, i in enumerate(bytes_):
            spelt[i] = bytes([b])
        self.spelt = np.frombuffer(b"".join(spelt), np.uint8)
        self.spelt_first = np.concatenate(([0], np.cumsum([len(x) for x in spelt])))

    @classmethod
    def load(cls, path: str) -> PieceModel:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        kinds = {i: sp.id_to_piece(i) for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i))}
        normal = {i: p for i, p in kinds.items() if not sp.is_byte(i)}
        spelt = {p: i for i, p in kinds.items() if sp.is_byte(i)}
        scores = np.array([sp.get_score(i) for i in normal])
        merges = bool((scores[:1000] == np.floor(scores[:1000])).all())  # whole numbers are ranks
        return cls([p.replace(chr(MARK), " ") for p in normal.values()], scores.tolist(), list(normal), [spelt[f"<0x{b:02X}>"] for b in range(256)], merges)

    def _learn_merges(self) -> None:
        """Ranks, the last merge of each piece, and which two pieces join into which.

        A piece that merging never makes of its own text is closed off.
        """
        n = len(self.pieces)
        self.order = np.empty(n, np.int64)
        self.order[np.argsort(-self.scores, kind="stable")] = np.arange(n)
        self.left, self.right = np.arange(n), np.arange(n)
        self.made = np.ones(n, bool)
        order = self.order.tolist()
        for i, p in enumerate(self.pieces):
            if len(p) > 1:
                parts = [self.by_text.get(c, -1) for c in p]
                while len(parts) > 1:
                    joins = [(order[j], k, j) for k in range(len(parts) - 1) if min(parts[k], parts[k + 1]) >= 0 and (j := self.by_text.get(self.pieces[parts[k]] + self.pieces[parts[k + 1]], -1)) >= 0]
                    if not joins:
                        break
                    _, k, j = min(joins)
                    if len(parts) == 2:
                        self.left[i], self.right[i] = parts
                    parts[k : k + 2] = [j]
                self.made[i] = parts == [i]
        pairs, whole = [], []
        for i, p in enumerate(self.pieces):
            for cut in range(1, len(p)):
                a, b = self.by_text.get(p[:cut]), self.by_text.get(p[cut:])
                if a is not None and b is not None:
                    pairs.append(a << 32 | b)
                    whole.append(order[i])
        keys = np.array(pairs, np.uint64)
        self.pair_table, self.pair_rank = KeyTable(keys), np.append(np.array(whole, np.int64), np.iinfo(np.int64).max)

    def _adjoin_cached(self, first: np.ndarray, second: np.ndarray) -> np.ndarray:
        """Through a table of fixed size in which a later pair takes an earlier one's place."""
        keys = first.astype(np.uint64) << np.uint64(32) | second.astype(np.uint64)
        at = ((keys * _BASE) >> np.uint64(64 - _CACHE)).astype(np.int64)
        out = self.cached[at]
        new = np.flatnonzero(self.cached_key[at] != keys)
        if len(new):
            out[new] = self._adjoin(first[new], second[new])
            self.cached_key[at[new]] = keys[new]
            # where two of these pairs share a place, both writes must be of the pair that stays
            stays = self.cached_key[at[new]] == keys[new]
            self.cached[at[new[stays]]] = out[new[stays]]
        return out

    def _adjoin(self, first: np.ndarray, second: np.ndarray) -> np.ndarray:
        """For each pair of pieces, whether merging leaves their border alone.

        Going back through the merges of both, the latest first: at each point the two parts at the border
        must not join at a rank that merging would have taken before the parts themselves were made.
        """
        keys, back = np.unique(first.astype(np.uint64) << np.uint64(32) | second.astype(np.uint64), return_inverse=True)
        a, b = (keys >> np.uint64(32)).astype(np.int64), (keys & np.uint64(0xFFFFFFFF)).astype(np.int64)
        fine = self.made[a] & self.made[b]
        # a join counts if it comes before the step that is being undone; on equal ranks the one further left does
        limit = np.full(len(a), np.iinfo(np.int64).max - 1)
        todo = np.flatnonzero(fine)
        while len(todo):
            x, y = a[todo], b[todo]
            rank = self.pair_rank[self.pair_table.find(x.astype(np.uint64) << np.uint64(32) | y.astype(np.uint64))]
            broken = rank < limit[todo]
            fine[todo[broken]] = False
            todo, x, y = todo[~broken], x[~broken], y[~broken]
            whole_x, whole_y = self.left[x] == x, self.left[y] == y
            rank_x, rank_y = np.where(whole_x, -1, self.order[x]), np.where(whole_y, -1, self.order[y])
            undo_x = rank_x > rank_y
            limit[todo] = np.where(undo_x, rank_x, rank_y + 1)
            a[todo] = np.where(undo_x, self.right[x], x)
            b[todo] = np.where(undo_x, y, self.left[y])
            todo = todo[~(whole_x & whole_y)]
        return fine[back]

    @staticmethod
    def _key(text: str) -> int:
        h = 0
        for x in _hash(np.array([ord(c) for c in text])).tolist():
            h = (h * int(_BASE) + x) % (1 << 64)
        return h

    def _spell(self, point: int) -> list[int]:
        return self.bytes_[list(chr(point).encode("utf-8", "replace"))].tolist()

    def _single(self, points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The recurrence for one run of characters: ends of its pieces and their numbers, -2 for a spelt character.

        The pieces that end at each place are found for all places at once; what is left to do one by one
        is to take the best of them.
        """
        n = len(points)
        up, down = powers(n)
        prefix = np.zeros(n + 1, np.uint64)
        np.cumsum(_hash(points) * down[:n], out=prefix[1:])
        ends, pieces = [], []
        for size in range(min(n, self.longest), 0, -1):
            key = (prefix[size:] - prefix[: n + 1 - size]) * up[size - 1 : n]
            at = np.flatnonzero(self.maybe[(key >> np.uint64(64 - _FILTER)).astype(np.int64)])
            found = np.minimum(np.searchsorted(self.keys, key[at]), len(self.keys) - 1)
            hit = self.keys[found] == key[at]
            ends.append(at[hit] + size)
            pieces.append(self.rank[found[hit]])
        size_of = np.repeat(np.arange(min(n, self.longest), 0, -1), list(map(len, ends)))
        end, piece = np.concatenate(ends), np.concatenate(pieces)
        order = np.argsort(end, kind="stable")  # at each end the longest first
        first = np.searchsorted(end[order], np.arange(n + 2)).tolist()
        sizes, pieces, scores = size_of[order].tolist(), piece[order].tolist(), self.scores[piece[order]].tolist()
        best, size_at, piece_at = [0.0] * (n + 1), [1] * (n + 1), [-2] * (n + 1)
        for e in range(1, n + 1):
            top = best[e - 1] + self.unknown
            for k in range(first[e], first[e + 1]):
                size, i = sizes[k], pieces[k]
                got = best[e - size] + scores[k]
                if got > top and (not self.merges or self._may_follow(piece_at[e - size] if size < e else -2, i)):
                    top, size_at[e], piece_at[e] = got, size, i
                    if self.merges:
                        break  # with merges, one piece may end here
            best[e] = top
        out, e = [], n
        while e:
            out.append(e)
            e -= size_at[e]
        out = np.array(out[::-1])
        return out, np.array(piece_at)[out]

    def _may_follow(self, before: int, piece: int) -> bool:
        """before is -2 at a run's start and for a spelt character."""
        if before < 0:
            return bool(self.made[piece])
        key = before << 32 | piece
        if key not in self.known:
            if len(self.known) >= 1 << _CACHE:
                self.known.clear()
            self.known[key] = bool(self._adjoin(np.array([before]), np.array([piece]))[0])
        return self.known[key]

    def _equal(self, words: np.ndarray) -> np.ndarray:
        """Segments the rows of a matrix: piece numbers by column of their last character, -1 where none ends
        and -2 for a spelt character."""
        n, length = words.shape
        value = _hash(words)
        prefix = np.zeros((length + 1, n), np.uint64)
        for j in range(length):
            prefix[j + 1] = prefix[j] * _BASE + value[:, j]
        up, _ = powers(self.longest)
        best = np.zeros((length + 1, n))
        size_of, piece_of = np.ones((length + 1, n), np.int16), np.full((length + 1, n), -2, np.int32)
        shift = np.uint64(64 - _FILTER)
        for e in range(1, length + 1):
            top = best[e - 1] + self.unknown
            open_ = np.arange(n)  # with merges, a row is done with the one piece that may end here
            for size in range(min(e, self.longest), 0, -1):
                some = open_ if len(open_) < n else slice(None)
                key = prefix[e][some] - prefix[e - size][some] * up[size]
                at = open_[self.maybe[(key >> shift).astype(np.int64)]]
                if not len(at):
                    continue
                key = prefix[e][at] - prefix[e - size][at] * up[size]
                found = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
                hit = self.keys[found] == key
                at, piece = at[hit], self.rank[found[hit]]
                if self.merges and len(at):
                    before = piece_of[e - size][at] if size < e else np.full(len(at), -2)
                    free = self.made[piece]
                    inner = before >= 0
                    free[inner] = self._adjoin_cached(before[inner], piece[inner])
                    at, piece = at[free], piece[free]
                score = best[e - size][at] + self.scores[piece]
                better = score > top[at]  # the longer piece came first and keeps ties
                at = at[better]
                if self.merges and len(at):
                    left = np.ones(n, bool)
                    left[at] = False
                    open_ = open_[left[open_]]
                top[at], size_of[e][at], piece_of[e][at] = score[better], size, piece[better]
            best[e] = top
        out = np.full((n, length), -1, np.int32)
        end = np.full(n, length)
        rows = np.arange(n)
        while len(rows):
            e = end[rows]
            out[rows, e - 1] = piece_of[e, rows]
            end[rows] = e - size_of[e, rows]
            rows = rows[end[rows] > 0]
        return out

    def _paths(self, points: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of each run points[start:end]: (run, end of a piece in points, piece or -2), in order."""
        lengths = end - start
        parts = [(np.zeros(0, np.int64),) * 3]
        for length in np.unique(lengths):
            which = np.flatnonzero(lengths == length)
            if length > self.window and len(which) < self.longest:  # a matrix pays from about so many rows on
                for w in which:
                    at, piece = self._single(points[start[w] : end[w]])
                    parts.append((np.full(len(at), w), start[w] + at, piece))
                continue
            for lo in range(0, len(which), _ROWS):
                some = which[lo : lo + _ROWS]
                got = self._equal(points[start[some][:, None] + np.arange(length)])
                row, column = np.nonzero(got != -1)
                parts.append((some[row], start[some][row] + column + 1, got[row, column]))
        run, at, piece = (np.concatenate(x) for x in zip(*parts, strict=True))
        order = np.lexsort((at, run))
        return run[order], at[order], piece[order]

    def _cut(self, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Runs longer than a window as overlapping windows; without merges, as they are."""
        step = self.window - self.overlap
        pieces = np.where(end - start > self.window, -(-(end - start - self.overlap) // step), 1) if self.merges else np.ones(len(start), np.int64)
        lo = np.repeat(start, pieces) + (np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces)) * step
        whole = np.repeat(end, pieces)
        return lo, np.where(np.repeat(pieces, pieces) > 1, np.minimum(lo + self.window, whole), whole)

    def _joined(self, points: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ends of pieces in points, and the pieces, of back-to-back or separate runs, through windows.

        Where two neighbouring windows have the same piece at the same place, the first one's path up to there and
        the second one's from there on are one path of pieces that may adjoin, and there is one such path only.
        Neighbours without such a piece become one window and are done again.
        """
        lo, hi = self._cut(start, end)
        todo, weight = np.arange(len(lo)), np.ones(len(lo), np.int64)
        run = at = piece = np.zeros(0, np.int64)
        while True:
            r, a, p = self._paths(points, lo[todo], hi[todo])
            run, at, piece = np.concatenate((run, todo[r])), np.concatenate((at, a)), np.concatenate((piece, p))
            order = np.lexsort((run, at))
            run, at, piece = run[order], at[order], piece[order]
            meets = np.zeros(len(lo), bool)  # the next window overlaps this one
            meets[:-1] = lo[1:] < hi[:-1]
            same = (at[1:] == at[:-1]) & (piece[1:] == piece[:-1]) & (run[1:] == run[:-1] + 1)
            join = np.full(len(lo), -1)
            join[run[:-1][same]] = at[:-1][same]
            apart = meets & (join < 0)
            if not apart.any():
                break
            for i in np.flatnonzero(apart).tolist():  # a window at least doubles, so it is done again a few times only
                more = weight[i]
                while meets[i] and more > 0:
                    apart[i] = True
                    i += 1
                    more -= weight[i]
            head = np.concatenate(([True], ~apart[:-1]))  # windows that start a merged one
            group = np.cumsum(head) - 1
            weight = np.bincount(group, weights=weight).astype(np.int64)
            merged = np.bincount(group) > 1
            lo, hi = lo[head], hi[np.append(np.flatnonzero(head)[1:] - 1, len(hi) - 1)]
            keep = ~merged[group[run]]
            run, at, piece = group[run[keep]], at[keep], piece[keep]
            todo = np.flatnonzero(merged)
        after = np.concatenate(([-1], np.where(meets, join, -1)[:-1]))
        until = np.where(meets, join, np.iinfo(np.int64).max)
        keep = (at > after[run]) & (at <= until[run])
        return at[keep], piece[keep]

    def segment(self, points: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the words points[start:end], start ascending, back to back, and offsets."""
        if not len(start):
            return np.zeros(0, np.int32), np.zeros(1, np.int64)
        at, piece = self._joined(points, start, end)
        spelt = np.flatnonzero(piece < 0)
        spellings = [self._spell(int(points[at[i] - 1])) for i in spelt]
        count = np.ones(len(at), np.int64)
        count[spelt] = list(map(len, spellings))
        first = np.cumsum(count) - count
        ids = np.repeat(self.ids[np.maximum(piece, 0)], count)
        for i, codes in zip(first[spelt].tolist(), spellings, strict=True):
            ids[i : i + len(codes)] = codes
        word = np.searchsorted(start, at - 1, side="right") - 1
        return ids, np.concatenate(([0], np.cumsum(np.bincount(word, weights=count, minlength=len(start)).astype(np.int64))))

    def encode(self, column: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Per block: the texts' ids back to back, and offsets."""
        for block in blocks(column, PIECE_BLOCK):
            yield self._encode(block)

    def _encode(self, block: Block) -> tuple[np.ndarray, np.ndarray]:
        starts_char = (block.data & 0xC0) != 0x80
        at = np.concatenate(([0], np.cumsum(starts_char)))[block.offsets]
        plain = np.frombuffer(block.data.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
        sizes = np.diff(at)
        lead = (sizes > 0).astype(np.int64)
        first = np.concatenate(([0], np.cumsum(sizes + lead)))
        points = np.full(first[-1], SPACE, np.uint32)
        points[np.arange(len(plain)) + np.repeat(np.cumsum(lead), sizes)] = plain
        if not len(points):
            return np.zeros(0, np.int32), np.zeros(block.n + 1, np.int64)
        space = points == SPACE
        opens = space.copy()
        opens[1:] &= ~space[:-1]
        opens[first[:-1][lead > 0]] = True
        start = np.flatnonzero(opens)
        end = np.append(start[1:], len(points))
        up, down = powers(len(points))
        prefix = np.zeros(len(points) + 1, np.uint64)
        np.cumsum(_hash(points) * up[: len(points)], out=prefix[1:])
        code = mix64((prefix[end] - prefix[start]) * down[start] + (end - start).astype(np.uint64))
        _, one, back = np.unique(code, return_index=True, return_inverse=True)
        order = np.argsort(one)  # in order of their places
        place = np.empty_like(order)
        place[order] = np.arange(len(order))
        one, back = one[order], place[back]
        ids, cut = self.segment(points, start[one], end[one])
        count = np.diff(cut)[back]
        out_at = np.cumsum(count) - count
        out = ids[np.repeat(cut[:-1][back] - out_at, count) + np.arange(count.sum())]
        per_word = np.concatenate(([0], np.cumsum(count)))
        return out, per_word[np.searchsorted(start, first)]

    def decode(self, ids: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Bytes of the texts back to back, and offsets."""
        size = np.diff(self.spelt_first)[ids]
        at = np.cumsum(size) - size
        data = self.spelt[np.repeat(self.spelt_first[:-1][ids] - at, size) + np.arange(size.sum())]
        cut = np.concatenate(([0], np.cumsum(size)))[first]
        some = np.flatnonzero(np.diff(cut))
        keep = np.ones(len(data), bool)
        keep[cut[:-1][some]] = False  # the space put in front
        return data[keep], cut - np.concatenate(([0], np.cumsum(np.diff(cut) > 0)))


@lru_cache(maxsize=2)
def load(path: str) -> PieceModel:
    return PieceModel.load(path)


def encode(docs: DataFrame, model: PieceModel, text_column: str = "text", digest: bool = False) -> DataFrame:
    """docs without the text, with n_pieces and ids; or, with digest, n_pieces, ids_sha256 (of the ids as
    little-endian 32-bit numbers), decoded_sha256 (of the decoded bytes) and round_trip."""
    shared, names = docs.sparkSession.sparkContext.broadcast(model), docs.columns
    at = names.index(text_column)
    added = ["n_pieces", "ids_sha256", "decoded_sha256", "round_trip"] if digest else ["n_pieces", "ids"]
    kept = [i for i, x in enumerate(names) if i != at and x not in added]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lo = 0
            for block in blocks(batch.column(at), PIECE_BLOCK):
                ids, first = shared.value._encode(block)
                rows = [batch.column(i).slice(lo, block.n) for i in kept]
                lo += block.n
                if digest:
                    data, cut = shared.value.decode(ids, first)
                    same = np.diff(cut) == block.lengths
                    same &= (len(data) == len(block.data)) and bool((data == block.data).all()) or _same(data, cut, block)
                    little = ids.astype("<i4")
                    marks = [[hashlib.sha256(x[a:b].tobytes()).hexdigest() for a, b in zip(c[:-1], c[1:], strict=True)] for x, c in ((little, first), (data, cut))]
                    made = [pa.array(np.diff(first)), pa.array(marks[0]), pa.array(marks[1]), pa.array(same)]
                else:
                    made = [pa.array(np.diff(first)), pa.ListArray.from_arrays(pa.array(first.astype(np.int32)), pa.array(ids))]
                yield pa.RecordBatch.from_arrays([*rows, *made], names=[*(names[i] for i in kept), *added])
            batch = block = ids = first = rows = made = None
            give_back()

    schema = T.StructType([docs.schema.fields[i] for i in kept]).add("n_pieces", "long")
    schema = schema.add("ids_sha256", "string").add("decoded_sha256", "string").add("round_trip", "boolean") if digest else schema.add("ids", T.ArrayType(T.IntegerType()))
    return docs.mapInArrow(run, schema)


def _same(data: np.ndarray, cut: np.ndarray, block: Block) -> np.ndarray:
    return np.array([bytes(data[a:b]) == bytes(block.data[c:d]) for a, b, c, d in zip(cut[:-1], cut[1:], block.offsets[:-1], block.offsets[1:], strict=True)])


def decode(docs: DataFrame, model: PieceModel, ids_column: str = "ids") -> DataFrame:
    """docs with text in place of the ids; null ids give an empty text."""
    shared, names = docs.sparkSession.sparkContext.broadcast(model), docs.columns
    at = names.index(ids_column)
    kept = [i for i, x in enumerate(names) if i != at and x != "text"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                lists = batch.column(at)
                sizes = np.array([len(x) if x.is_valid else 0 for x in lists])
                data, cut = shared.value.decode(lists.flatten().to_numpy(zero_copy_only=False), np.concatenate(([0], np.cumsum(sizes))))
                text = pa.LargeStringArray.from_buffers(len(sizes), pa.py_buffer(cut.astype(np.int64).tobytes()), pa.py_buffer(data.tobytes()))
                yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in kept), text.cast(pa.string())], names=[*(names[i] for i in kept), "text"])

    return docs.mapInArrow(run, T.StructType([docs.schema.fields[i] for i in kept]).add("text", "string"))
