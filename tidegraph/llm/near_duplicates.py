"""MinHash near-duplicates with odd sketches.

Each document is a set of word shingles. MinHash samples are banded for candidates, and folded into
a parity bitmap (the odd sketch): the bits in which two bitmaps differ count the samples in which
the documents differ, which tells high similarities apart at 128 bytes a document. Candidates that
pass this test are confirmed on the full sets, so no false link remains; the chance that a pair at
exactly the threshold shares no band is about 1e-8 or less.

Groups of copies never turn into all their pairs. Documents with equal sets collapse to one
representative first. Then each band's bucket links its members to one of them only, the one that
meets most others over all bands; a second round compares just those members of a bucket that the
confirmed links have left in different components, chunk by chunk, by parity bitmaps of the full sets, which rule out most pairs
just below the threshold and never a link.

Cases: null or blank texts have an empty set and link with nothing; a document of fewer words than
a shingle has one shingle, the whole sequence; repeated rows and ids are all kept, and equal ids
are one vertex; a null id links with nothing and has a null component; an empty table gives an
empty result.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidegraph.llm.common import give_back, per_batch, small_side
from tidegraph.llm.textblocks import Block, blocks, mix64, seeds, shingles, sorted_sets, spaced_words, word_codes
from tidegraph.operators.components import connected_components
from tidegraph.plans.scratch import Scratch


@dataclass(frozen=True)
class NearDuplicates:
    """Links documents whose shingle sets have Jaccard similarity of at least percent / 100."""

    width: int = 5
    percent: int = 80
    bands: int = 32
    rows: int = 4
    words: int = 16  # of 64 bits in an odd sketch
    parity_words: int = 48  # of 64 bits in the parity bitmap of a full set

    @property
    def samples(self) -> int:
        return self.bands * self.rows

    @property
    def most_bits(self) -> int:
        """Differing sketch bits that a pair at the threshold exceeds by six deviations only.

        Each differing sample flips a bit in both bitmaps, and flips can only cancel.
        """
        p = 1 - self.percent / 100
        return math.ceil(2 * (self.samples * p + 6 * math.sqrt(self.samples * p * (1 - p)) + 2))


def shingle_sets(block: Block, width: int) -> tuple[np.ndarray, np.ndarray]:
    words = spaced_words(block)
    return sorted_sets(*shingles(word_codes(block, words), words.first, width))


def minhash(values: np.ndarray, first: np.ndarray, samples: int) -> np.ndarray:
    """samples x documents; each document must have a value."""
    scale, shift = seeds(samples, 11) | np.uint64(1), seeds(samples, 12)
    out = np.empty((samples, len(first) - 1), np.uint64)
    work = np.empty_like(values)
    for i in range(samples):
        np.multiply(values, scale[i], out=work)
        work += shift[i]
        np.minimum.reduceat(work, first[:-1], out=out[i])
    return out


def odd_sketch(samples: np.ndarray, words: int) -> np.ndarray:
    """documents x words of 64 bits: the parity of how many samples fall on each bit."""
    k, n = samples.shape
    bits = np.zeros((n, words * 64), np.uint8)
    rows = np.arange(n)
    for i, at in enumerate(mix64(samples + seeds(k, 13)[:, None]) % np.uint64(words * 64)):
        bits[rows, at.astype(np.int64)] ^= 1
    return np.packbits(bits, axis=1).view(np.int64)


def band_keys(samples: np.ndarray, bands: int) -> np.ndarray:
    """documents x bands of 64-bit keys, no two bands sharing keys."""
    k, n = samples.shape
    weighted = samples.reshape(bands, k // bands, n) * seeds(k // bands, 14)[None, :, None]
    return mix64(weighted.sum(axis=1, dtype=np.uint64) + seeds(bands, 15)[:, None]).T.view(np.int64)


def _lists(matrix: np.ndarray) -> pa.Array:
    n, k = matrix.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * k), pa.array(np.ascontiguousarray(matrix).reshape(-1)))


def sketches(docs: DataFrame, how: NearDuplicates) -> DataFrame:
    """id, n (set size), d1 and d2 (digest of the set), keys, odd; keys and odd are empty for empty sets."""

    def one(batch: pa.RecordBatch) -> pa.RecordBatch:
        sizes, digests, keys, odds = [], [], [], []
        for block in blocks(batch.column(1)):
            values, first = shingle_sets(block, how.width)
            n = np.diff(first)
            some = np.flatnonzero(n)
            d = np.zeros((2, block.n), np.uint64)
            k, o = np.zeros((block.n, how.bands), np.int64), np.zeros((block.n, how.words), np.int64)
            if len(some):
                starts = first[:-1][some]
                for j in range(2):
                    d[j, some] = np.add.reduceat(mix64(values + seeds(2, 16)[j]), starts)
                drawn = minhash(values, np.append(starts, len(values)), how.samples)
                k[some], o[some] = band_keys(drawn, how.bands), odd_sketch(drawn, how.words)
            sizes.append(n)
            digests.append(d.view(np.int64))
            keys.append(k)
            odds.append(o)
        both = np.concatenate(digests, axis=1)
        return pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(np.concatenate(sizes)), pa.array(both[0]), pa.array(both[1]), _lists(np.concatenate(keys)), _lists(np.concatenate(odds))],
            names=["id", "n", "d1", "d2", "keys", "odd"],
        )

    return per_batch(docs.select("id", "text"), one, "id bigint, n bigint, d1 bigint, d2 bigint, keys array<bigint>, odd array<bigint>")


def _full_sets(docs: DataFrame, ids: DataFrame, rows: int, width: int) -> DataFrame:
    """The shingle sets of the given ids alone; texts are shuffled only if the ids are too many to broadcast."""

    def one(batch: pa.RecordBatch) -> pa.RecordBatch:
        parts, counts = [], []
        for block in blocks(batch.column(1)):
            values, first = shingle_sets(block, width)
            parts.append(values.view(np.int64))
            counts.append(np.diff(first))
        offsets = np.concatenate(([0], np.cumsum(np.concatenate(counts)))).astype(np.int32)
        return pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(parts)))], names=["id", "members"])

    chosen = docs.join(small_side(ids, rows), "id", "left_semi").select("id", "text")
    return per_batch(chosen, one, "id bigint, members array<bigint>")


def _parities(docs: DataFrame, ids: DataFrame, rows: int, how: NearDuplicates) -> DataFrame:
    """The parity bitmaps of the full sets of the given ids."""

    def one(batch: pa.RecordBatch) -> pa.RecordBatch:
        out = []
        for block in blocks(batch.column(1)):
            values, first = shingle_sets(block, how.width)
            at = (mix64(values + seeds(1, 17)) % np.uint64(how.parity_words * 64)).astype(np.int64)
            at += np.repeat(np.arange(block.n), np.diff(first)) * how.parity_words * 64
            bits = np.bincount(at, minlength=block.n * how.parity_words * 64).astype(np.uint8) & 1
            out.append(np.packbits(bits).view(np.int64).reshape(block.n, how.parity_words))
        return pa.RecordBatch.from_arrays([batch.column(0), _lists(np.concatenate(out))], names=["id", "parity"])

    chosen = docs.join(small_side(ids, rows), "id", "left_semi").select("id", "text")
    return per_batch(chosen, one, "id bigint, parity array<bigint>")


#: Members of one bucket that are compared with each other in one piece.
CHUNK = 512
#: Pairs of one document that meet its set or sketch in one task.
HOT = 2048


def _compare(piece: dict[str, np.ndarray], how: NearDuplicates) -> tuple[np.ndarray, np.ndarray]:
    """Positions of pairs in different components whose parity bitmaps admit a link.

    Sets that differ in d members have bitmaps that differ in d bits at most, so no link is lost.
    """
    component, n, bits = piece["component"], piece["n"], piece["parity"]
    left = np.flatnonzero(piece["side"] == 0)
    right = np.flatnonzero(piece["side"] == 1) if piece["i"][0] != piece["j"][0] else left
    names, counts = np.unique(component, return_counts=True)
    most = names[counts.argmax()]  # pairs inside the largest component need no look
    if left is right:
        left = left[component[left] != most]
    found_a, found_b = [], []
    step = max(1, (1 << 22) // max(1, len(right) * bits.shape[1]))
    for at in range(0, len(left), step):
        rows = left[at : at + step]
        apart = np.bitwise_count(bits[rows][:, None, :] ^ bits[right][None, :, :]).sum(axis=2, dtype=np.int64)
        fit = (100 + how.percent) * apart <= (100 - how.percent) * (n[rows][:, None] + n[right][None, :])
        x, y = np.nonzero(fit & (component[rows][:, None] != component[right][None, :]))
        found_a.append(rows[x])
        found_b.append(right[y])
    none = np.zeros(0, np.int64)
    return np.concatenate([none, *found_a]), np.concatenate([none, *found_b])


def _across(known: DataFrame, how: NearDuplicates) -> DataFrame:
    """Pairs (a, b) that share a bucket and not a component, for the test on full sets.

    known: key, size (of the bucket), most (its largest component), inside (members of that), id, component, n,
    parity. A large bucket is cut into chunks by a hash of the id, members of its largest component apart, and each
    two chunks meet in a piece of their own, but for chunks of that component, which needs no look. So a bucket of
    copies of one text with few others is moved once or twice, whatever its size.
    """
    cut = known.withColumn("others", F.expr(f"cast(ceil((size - inside) / {CHUNK}) as int)")).withColumn("chunks", F.expr(f"others + cast(ceil(inside / {CHUNK}) as int)"))
    cut = cut.withColumn("own", F.expr("cast(if(component = most, others + pmod(xxhash64(id, key), chunks - others), pmod(xxhash64(id, key), others)) as int)"))
    pieces = (
        cut.withColumn("other", F.explode(F.expr("sequence(0, if(component = most, others, chunks) - 1)")))
        .select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), F.expr("if(own <= other, 0, 1)").alias("side"), "id", "component", "n", "parity")
        .repartition("key", "i", "j")
        .sortWithinPartitions("key", "i", "j")
    )

    def run(batches):
        kept: dict[str, np.ndarray] | None = None
        for batch in batches:
            if not batch.num_rows:
                continue
            lists = batch.column("parity")
            now = {k: batch.column(k).to_numpy() for k in ("key", "i", "j", "side", "id", "component", "n")}
            now["parity"] = lists.flatten().to_numpy().view(np.uint64).reshape(batch.num_rows, how.parity_words)
            if kept is not None:
                now = {k: np.concatenate((kept[k], now[k])) for k in now}
            new = np.flatnonzero((now["key"][1:] != now["key"][:-1]) | (now["i"][1:] != now["i"][:-1]) | (now["j"][1:] != now["j"][:-1])) + 1
            cuts = np.concatenate(([0], new))
            yield pairs(now, cuts)
            kept = {k: v[cuts[-1] :].copy() for k, v in now.items()}
        if kept is not None:
            yield pairs(kept, np.array([0, len(kept["key"])]))
        now = kept = None
        give_back()

    def pairs(rows: dict[str, np.ndarray], cuts: np.ndarray) -> pa.RecordBatch:
        a, b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
            if hi - lo > 1:
                piece = {k: v[lo:hi] for k, v in rows.items()}
                x, y = _compare(piece, how)
                a.append(piece["id"][x])
                b.append(piece["id"][y])
        a, b = np.concatenate(a), np.concatenate(b)
        both = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)]), axis=1)
        return pa.RecordBatch.from_arrays([pa.array(both[0]), pa.array(both[1])], names=["a", "b"])

    return pieces.mapInArrow(run, "a bigint, b bigint").where("a < b").distinct()


def _alike(a: str, b: str, how: NearDuplicates):
    """Odd sketches a and b differ in few enough bits, and set sizes admit the similarity."""
    bits = " + ".join(f"bit_count({a}.odd[{i}] ^ {b}.odd[{i}])" for i in range(how.words))
    return F.expr(f"100 * least({a}.n, {b}.n) >= {how.percent} * greatest({a}.n, {b}.n) and {bits} <= {how.most_bits}")


def _beside(rows: DataFrame, pairs: DataFrame, column: str, table: DataFrame, scratch: Scratch, tag: str) -> DataFrame:
    """rows (which hold pairs a, b) with the row of table (id, ...) for the id in column.

    An id of over HOT pairs, such as that of a text with many copies, is dealt over several tasks, its row repeated.
    """
    table, other = table.withColumnRenamed("id", column), "b" if column == "a" else "a"
    hot = pairs.groupBy(column).agg(F.count(F.lit(1)).alias("c")).where(F.col("c") > HOT).select(column, F.ceil(F.col("c") / HOT).alias("parts"))
    hot = scratch.save(hot, f"hot-{tag}-{column}")
    n = hot.count()
    if not n:
        return rows.join(table, column)
    hot, parts = small_side(hot, n), F.coalesce("parts", F.lit(1))
    dealt = rows.join(hot, column, "left").withColumn("salt", F.pmod(F.xxhash64(other), parts)).drop("parts")
    copies = table.join(hot, column, "left").withColumn("salt", F.explode(F.sequence(F.lit(0), parts - 1))).drop("parts")
    return dealt.join(copies, [column, "salt"]).drop("salt")


def _confirm(pairs: DataFrame, docs: DataFrame, how: NearDuplicates, scratch: Scratch, tag: str) -> DataFrame:
    """The pairs (a, b) whose full sets reach the threshold."""
    ids = pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct()
    ids = scratch.save(ids, f"ids-{tag}")
    sets = scratch.save(_full_sets(docs, ids, ids.count(), how.width), f"sets-{tag}")
    met = _beside(pairs, pairs, "b", sets.withColumnRenamed("members", "mb"), scratch, f"sets-{tag}")
    met = _beside(met, pairs, "a", sets.withColumnRenamed("members", "ma"), scratch, f"sets-{tag}")
    met = met.select("a", "b", F.size("ma").alias("na"), F.size("mb").alias("nb"), F.size(F.array_intersect("ma", "mb")).alias("both"))
    out = scratch.save(met.where(f"100 * both >= {how.percent} * (na + nb - both)").select("a", "b").distinct(), f"links-{tag}")
    scratch.drop(f"sets-{tag}")
    return out


def near_duplicates(docs: DataFrame, how: NearDuplicates = NearDuplicates(), id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """(id, n_shingles, component_id), a row for each row of docs."""
    scratch = Scratch(docs.sparkSession, "near-duplicates")
    docs = docs.select(F.col(id_column).cast("bigint").alias("id"), F.col(text_column).alias("text"))
    drawn = scratch.save(sketches(docs, how), "sketches")
    filled = drawn.where("n > 0 and id is not null")
    classes = scratch.save(filled.groupBy("d1", "d2", "n").agg(F.min("id").alias("rep")), "classes")
    reps = scratch.save(
        filled.join(classes.select("d1", "d2", F.col("rep").alias("id")), ["d1", "d2", "id"], "left_semi").select("id", "n", "keys", "odd").dropDuplicates(["id", "n"]),
        "reps",
    )

    members = reps.select("id", F.explode("keys").alias("key"))
    buckets = members.groupBy("key").agg(F.min("id").alias("lo"), F.max("id").alias("hi"), F.count("id").alias("size")).where("lo < hi").select("key", "size")
    shared = scratch.save(members.join(buckets, "key").select("key", "id", "size"), "shared")
    # the member that meets most others over all its buckets is nearest to what they are copies of
    met = shared.groupBy("id").agg(F.sum("size").alias("met"))
    leads = shared.join(met, "id").groupBy("key").agg(F.max(F.struct("met", "id"))["id"].alias("lead"))
    pair = F.least("id", "lead").alias("a"), F.greatest("id", "lead").alias("b")
    starred = scratch.save(shared.join(leads, "key").where("id <> lead").select(*pair).distinct(), "starred")
    x, y = (reps.select("id", F.struct("n", "odd").alias(c)) for c in ("x", "y"))
    first = _beside(_beside(starred, starred, "a", x, scratch, "star"), starred, "b", y, scratch, "star").where(_alike("x", "y", how)).select("a", "b").distinct()
    links = _confirm(scratch.save(first, "pairs-1"), docs, how, scratch, "1")
    found = scratch.save(connected_components(links, scratch, "cc1"), "components-1")

    # what is left: members of one bucket in different components
    placed = shared.join(found, "id", "left").select("key", "size", "id", F.coalesce("component", "id").alias("component"))
    parts = placed.groupBy("key", "component").agg(F.count(F.lit(1)).alias("c")).groupBy("key").agg(F.count(F.lit(1)).alias("parts"), F.max(F.struct("c", "component")).alias("m"))
    mixed = parts.where("parts > 1").select("key", F.col("m.component").alias("most"), F.col("m.c").alias("inside"))
    rest = scratch.save(placed.join(mixed, "key"), "rest")
    ids = scratch.save(rest.select("id").distinct(), "rest-ids")
    parity = scratch.save(_parities(docs, ids, ids.count(), how), "parities")
    known = rest.join(reps.select("id", "n"), "id").join(parity, "id").select("key", "size", "most", "inside", "id", "component", "n", "parity")
    # a pair that some bucket's star has tested already needs no second test
    second = _across(known, how).join(starred, ["a", "b"], "left_anti")
    more = _confirm(scratch.save(second, "pairs-2"), docs, how, scratch, "2")
    if not more.isEmpty():
        found = scratch.save(connected_components(links.unionByName(more), scratch, "cc2"), "components-2")
    for name in ("shared", "rest", "reps", "parities"):
        scratch.drop(name)

    # an id of several rows may stand in several classes
    own = drawn.select("id", "n", "d1", "d2").join(classes, ["d1", "d2", "n"], "left")
    roots = own.join(found.withColumnRenamed("id", "rep"), "rep", "left")
    return roots.select("id", F.col("n").alias("n_shingles"), F.coalesce("component", "rep", "id").alias("component_id"))
