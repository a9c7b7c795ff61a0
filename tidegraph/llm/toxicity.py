"""Toxicity: averaged subword embeddings under a linear softmax, trained jointly in numpy.

A text is lower-cased (A-Z), other bytes than letters, digits and those from 0x80 on become word
ends, and each word is the bag of its character 3- to 5-grams with its ends marked, hashed into
2^bits rows of an embedding table. A segment of `segment` words is the average of its n-gram vectors;
the softmax over that average gives the segment's probability, and a text is as toxic as its most
toxic segment, so a long text can't dilute an insult. Misspellings and inflections share n-grams
with forms seen in training. In training, each document's steepest segment carries its label (in the first pass: the average of all).
A step of training touches the n-grams of its batch only, and weighs each of the batch's distinct words once; the rows
of n-grams that weigh nothing are left out of the table till training ends.

Since the model is linear after the average, each n-gram's embedding meets the softmax once, when
training ends; scoring looks up one number an n-gram.

Training takes about train_rows labelled documents at most, chosen by a hash of the id over all,
each with its whole text, and fewer of them if they have more than
train_bytes of text. n-grams met in fewer than min_docs of the texts trained on, an absolute number, weigh nothing.

Cases: null texts and texts without words get the intercept's score; with no labelled row every
score is 0.5, with one class it leans there; null and repeated ids are scored as they are; an empty
table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tidegraph.llm.common import bounded_rows, per_batch
from tidegraph.llm.textblocks import LOWER, Block, blocks, prefix_code, range_code, runs

_WORD = np.zeros(256, bool)
_WORD[48:58] = _WORD[65:91] = _WORD[97:123] = _WORD[128:] = True
_FOLD = np.where(_WORD, LOWER, 0).astype(np.uint64)


@dataclass(frozen=True)
class Toxicity:
    bits: int = 20
    dim: int = 8
    segment: int = 24
    train_rows: int = 8000
    train_bytes: int = 64 << 20
    kept_back: float = 0.25
    epochs: int = 6
    batch: int = 64
    rate: float = 0.7
    decay: float = 3e-2
    scale: float = 10.0
    min_docs: int = 15
    seed: int = 5


def segments(block: Block, how: Toxicity) -> tuple[np.ndarray, np.ndarray, list[tuple[np.ndarray, np.ndarray]]]:
    """First segment by document, n-grams by segment, and per length: hashes, and the segment of each (ascending)."""
    words = runs(block, _WORD[block.data])
    per_doc = np.diff(words.first)
    segs = -(-per_doc // how.segment)
    seg_first = np.concatenate(([0], np.cumsum(segs)))
    doc = words.doc
    seg_of_word = seg_first[doc] + (np.arange(len(doc)) - words.first[doc]) // how.segment
    # the words alone, each between two marks (0), which adjoining words share
    lengths = words.end - words.start
    n = int(lengths.sum()) + len(lengths) + 1
    text = np.zeros(n, np.uint64)
    starts = np.cumsum(lengths + 1) - lengths
    at = np.arange(int(lengths.sum())) + np.repeat(starts - (np.cumsum(lengths) - lengths), lengths)
    text[at] = _FOLD[block.data[np.repeat(words.start - (np.cumsum(lengths) - lengths), lengths) + np.arange(len(at))]]
    mark = text == 0
    inside = np.cumsum(mark)  # marks up to here
    word_of = np.maximum(inside - 1, 0)
    out = []
    shift = np.uint64(64 - how.bits)
    total = np.zeros(seg_first[-1], np.int64)
    key = text.copy()
    for length in range(2, 6):
        key = (key[: n - length + 1] << np.uint64(8)) | text[length - 1 :] if n >= length else key[:0]
        if length < 3 or not len(key):
            continue
        # no mark strictly inside
        fine = inside[length - 2 : n - 1] == inside[: n - length + 1]
        hashed = ((key[fine] + np.uint64(length)) * np.uint64(0x9E3779B97F4A7C15)) >> shift
        seg = seg_of_word[np.minimum(word_of[: n - length + 1][fine], len(seg_of_word) - 1)]
        out.append((hashed.astype(np.int32), seg))
        total += np.bincount(seg, minlength=len(total))
    return seg_first, total, out


def distinct(values: np.ndarray, place: np.ndarray) -> np.ndarray:
    """The distinct values in any order; place, with an entry for each value there may be, then holds where each is."""
    at = np.arange(len(values))
    place[values] = at
    found = values[place[values] == at]
    place[found] = at[: len(found)]
    return found


class WordBags:
    """The training texts as numbers of distinct words, and the n-grams of each word."""

    def __init__(self, texts: pa.ChunkedArray, how: Toxicity):
        number: dict[int, int] = {}
        spelt: list[bytes] = []
        self.words: list[np.ndarray] = []
        for column in texts.chunks:
            for block in blocks(column):
                found = runs(block, _WORD[block.data])
                codes, first, back = np.unique(range_code(prefix_code(LOWER[block.data]), found.start, found.end), return_index=True, return_inverse=True)
                own = np.empty(len(codes), np.int32)
                for k, (code, at) in enumerate(zip(codes.tolist(), first.tolist(), strict=True)):
                    own[k] = number.setdefault(code, len(spelt))
                    if own[k] == len(spelt):
                        spelt.append(block.data[found.start[at] : found.end[at]].tobytes())
                self.words += np.split(own[back], found.first[1:-1])
        hashes, words, done = [np.zeros(0, np.int32)], [np.zeros(0, np.int64)], 0
        for block in blocks(pa.array([w.decode("utf-8", "replace") for w in spelt], pa.string())):
            for hashed, seg in segments(block, how)[2]:
                hashes.append(hashed)
                words.append(seg + done)
            done += block.n
        hashes, words = np.concatenate(hashes), np.concatenate(words)
        order = np.argsort(words, kind="stable")
        self.grams = hashes[order]
        self.sizes = np.bincount(words, minlength=len(spelt))
        self.first = np.concatenate(([0], np.cumsum(self.sizes)))

    def grams_of(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where in grams the words' n-grams are, back to back, and where each word's begin; every word has some."""
        sizes = self.sizes[words]
        starts = np.cumsum(sizes) - sizes
        return np.repeat(self.first[words] - starts, sizes) + np.arange(sizes.sum()), starts

    def word_sums(self, words: np.ndarray, values: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """Sum over each word's n-grams of values, of which rows holds each n-gram's place."""
        at, starts = self.grams_of(words)
        return np.add.reduceat(values[rows[at]], starts)

    def segment_of(self, words: np.ndarray, gains: np.ndarray, segment: int) -> tuple[float, slice]:
        """The steepest segment's average gain, and where it is in words."""
        cut = np.arange(0, len(words), segment)
        mean = np.add.reduceat(gains, cut) / np.add.reduceat(self.sizes[words], cut)
        best = int(mean.argmax())
        return float(mean[best]), slice(best * segment, (best + 1) * segment)


class ToxicityModel:
    def __init__(self, how: Toxicity):
        self.how = how
        self.values = np.zeros(1 << how.bits, np.float32)  # what an n-gram adds to the log odds, before the average
        self.intercept = 0.0

    def fit(self, bags: WordBags, labels: np.ndarray) -> ToxicityModel:
        h, rng = self.how, np.random.default_rng(self.how.seed)
        if not len(labels):
            return self
        # a part is kept back, to place the threshold on texts not trained on
        spare = rng.random(len(labels)) < h.kept_back
        kept, used = np.flatnonzero(spare), np.flatnonzero(~spare)
        if not len(kept) or not len(used):
            kept = used = np.arange(len(labels))
        y = labels.astype(np.int64)
        # n-grams of too few documents would only be learnt by heart
        met = np.zeros(1 << h.bits, np.int32)
        place, word_place = np.zeros((1 << h.bits) + 1, np.int32), np.zeros(len(bags.sizes), np.int32)
        for d in used:
            met[distinct(bags.grams[bags.grams_of(distinct(bags.words[d], word_place))[0]], place)] += 1
        common = np.flatnonzero(met >= h.min_docs)
        # a row for each of the others' n-grams in one: zeros
        table = np.vstack([rng.normal(0, 0.01, (1 << h.bits, h.dim))[common], np.zeros((1, h.dim))]).astype(np.float32)
        rows = np.full(1 << h.bits, len(common), np.int32)
        rows[common] = np.arange(len(common))
        rows = rows[bags.grams]
        top = rng.normal(0, 1, (h.dim, 2)).astype(np.float32)
        top /= np.linalg.norm(top[:, 1] - top[:, 0])
        prior = (y[used].sum() + 1) / (len(used) + 2)
        bias = np.array([0.0, np.log(prior / (1 - prior))], np.float32)
        weight = np.where(y == 1, 0.5 / prior, 0.5 / (1 - prior)).astype(np.float32)
        for epoch in range(h.epochs):
            order = rng.permutation(used)
            rate = np.float32(h.rate * (1 - epoch / h.epochs))
            for lo in range(0, len(order), h.batch):
                part = [d for d in order[lo : lo + h.batch] if len(bags.words[d])]
                if not part:
                    continue
                words = [bags.words[d] for d in part]
                if epoch:  # else no segment stands out yet, and the average is over all
                    gains = bags.word_sums(distinct(np.concatenate(words), word_place), table @ (top[:, 1] - top[:, 0]), rows)
                    words = [own[bags.segment_of(own, gains[word_place[own]], h.segment)[1]] for own in words]
                doc = np.repeat(np.arange(len(part)), [len(own) for own in words])
                words = np.concatenate(words)
                total = np.bincount(doc, bags.sizes[words], len(part))
                i = rows[bags.grams_of(words)[0]]
                doc = np.repeat(doc, bags.sizes[words])
                w = (h.scale * (i < len(common)) / total[doc]).astype(np.float32)
                hidden = np.add.reduceat(table[i] * w[:, None], np.searchsorted(doc, np.arange(len(part))))
                z = hidden @ top + bias
                g = np.exp(z - z.max(axis=1, keepdims=True))
                g /= g.sum(axis=1, keepdims=True)
                g[np.arange(len(part)), y[part]] -= 1
                g *= weight[part][:, None]
                g_top, g_hidden = hidden.T @ g, g @ top.T
                u = distinct(i, place)
                back = place[i]
                for k in range(h.dim):
                    table[u, k] -= rate * (np.bincount(back, g_hidden[doc, k] * w, len(u)) + h.decay * table[u, k])
                top -= rate * 0.1 * g_top / len(part)
                bias -= rate * 0.1 * g.sum(axis=0) / len(part)
        self.values[common] = h.scale * (table[:-1] @ (top[:, 1] - top[:, 0]))
        self.intercept = float(bias[1] - bias[0])
        return self._place(np.array([self.log_odds(bags, d) for d in kept]), y[kept])

    def log_odds(self, bags: WordBags, d: int) -> float:
        own = bags.words[d]
        if not len(own):
            return self.intercept
        return self.intercept + float(bags.segment_of(own, bags.word_sums(own, self.values, bags.grams), self.how.segment)[0])

    def _place(self, odds: np.ndarray, y: np.ndarray) -> ToxicityModel:
        """Moves the intercept to where these documents are best told apart."""
        order = np.argsort(odds, kind="stable")
        wrong = np.concatenate(([0], np.cumsum(np.where(y[order] == 1, 1, -1))))
        at = np.flatnonzero(wrong == wrong.min())
        mid = at[len(at) // 2]
        lo, hi = (odds[order[mid - 1]] if mid else odds.min() - 1), (odds[order[mid]] if mid < len(odds) else odds.max() + 1)
        self.intercept -= float((lo + hi) / 2)
        return self

    def score(self, column: pa.Array) -> np.ndarray:
        out = []
        for block in blocks(column):
            seg_first, total, grams = segments(block, self.how)
            summed = np.zeros(len(total))
            for hashed, seg in grams:
                summed += np.bincount(seg, weights=self.values[hashed], minlength=len(total))
            mean = summed / np.maximum(total, 1)
            odds = np.full(block.n, self.intercept)
            some = np.flatnonzero(np.diff(seg_first))
            if len(some):
                odds[some] += np.maximum.reduceat(mean, seg_first[:-1][some])
            out.append(1 / (1 + np.exp(-np.clip(odds, -35, 35))))
        return np.concatenate(out)


def fit(docs: DataFrame, labels: DataFrame, how: Toxicity = Toxicity()) -> ToxicityModel:
    """docs: doc_id, text; labels: doc_id, label (0 or 1; others are left out)."""
    chosen = bounded_rows(labels.where("doc_id is not null and label in (0, 1)"), "doc_id", how.train_rows)
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen.select("doc_id", "label")), "doc_id").select("doc_id", "label", "text")
    long = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    if long > how.train_bytes:
        rows = rows.where(F.pmod(F.xxhash64("doc_id", F.lit(41)), F.lit(1 << 30)) < int((1 << 30) * how.train_bytes / long))
    got = rows.toArrow().sort_by([("doc_id", "ascending"), ("label", "ascending"), ("text", "ascending")])
    return ToxicityModel(how).fit(WordBags(got["text"], how), got["label"].to_numpy())


def score(docs: DataFrame, model: ToxicityModel, text_column: str = "text") -> DataFrame:
    """docs with score in place of the text column; a column of that name is replaced."""
    docs = docs.drop("score")
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names, text = docs.columns, docs.columns.index(text_column)
    kept = [i for i in range(len(names)) if i != text]

    def one(batch: pa.RecordBatch) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([*(batch.column(i) for i in kept), pa.array(shared.value.score(batch.column(text)))], names=[*(names[i] for i in kept), "score"])

    return per_batch(docs, one, T.StructType([docs.schema.fields[i] for i in kept]).add("score", "double"))
