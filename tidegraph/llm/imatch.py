"""I-Match fingerprints with randomised lexicons.

The lexicon is the terms whose share of documents lies in a band (an inverse-document-frequency
band: neither everyday words nor one-off ones). A document's distinct lexicon terms are sorted and
hashed once for each of several random subsets of the lexicon, from all of it down to a small part,
so that a small edit leaves most hashes alone. The fingerprint is those hashes in order; a subset
none of whose terms occur gives an empty field. Likeness is the share of fields that agree among
those where either has one; two empty fingerprints are alike only if equal texts made them.

A document without a lexicon term is fingerprinted by all its distinct terms instead, so no document
lacks a fingerprint.

The band's lower end bounds the lexicon: at most (distinct terms of a mean document) / least_share
terms reach it, however many documents there are, so it may be broadcast. Document frequencies are
counted over all texts, within partitions first.

Cases: null texts count as empty; an empty text has the fingerprint of no terms; null ids, repeated
rows and ids keep their rows; ties in doc_id are ordered by the texts' squeezed bytes; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tidegraph.llm.ppm import KeyTable, add_up
from tidegraph.llm.textblocks import LOWER, Block, blocks, mix64, prefix_code, range_code, runs, seeds, sorted_sets
from tidegraph.plans.scratch import Scratch

_TERM = np.zeros(256, bool)
_TERM[48:58] = _TERM[65:91] = _TERM[97:123] = _TERM[128:] = True


@dataclass(frozen=True)
class IMatch:
    least_share: float = 0.0005
    most_share: float = 0.05
    #: Part of the lexicon kept by each random subset.
    subsets: tuple[float, ...] = (1, 1 / 2, 1 / 4, *(1 / 8,) * 2, *(1 / 16,) * 5, *(1 / 32,) * 8, *(1 / 64,) * 12, *(1 / 128,) * 10)


def terms(block: Block) -> tuple[np.ndarray, np.ndarray]:
    """Distinct term codes by document, ascending, and offsets. Terms are runs of letters and digits, A-Z lowered."""
    words = runs(block, _TERM[block.data])
    return sorted_sets(range_code(prefix_code(LOWER[block.data]), words.start, words.end), words.first)


def document_frequencies(texts: DataFrame) -> DataFrame:
    """key, n over a column of texts."""

    def merge(held: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
        return add_up(np.concatenate([k for k, _ in held]), np.concatenate([c for _, c in held]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        for batch in batches:
            for block in blocks(batch.column(0)):
                held.append(np.unique(terms(block)[0], return_counts=True))
                if sum(len(k) for k, _ in held) > 1 << 20:  # bounds the worker's memory
                    held = [merge(held)]
                    if len(held[0][0]) > 1 << 19:
                        yield out(*held.pop())
        if held:
            yield out(*merge(held))

    def out(keys: np.ndarray, counts: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(counts)], names=["key", "n"])

    return texts.mapInArrow(run, "key bigint, n bigint").groupBy("key").agg(F.sum("n").alias("n"))


class Lexicon:
    def __init__(self, keys: np.ndarray, how: IMatch):
        self.how, self.keys = how, np.sort(keys)

    @classmethod
    def build(cls, docs: DataFrame, how: IMatch = IMatch()) -> Lexicon:
        n = docs.count()
        band = document_frequencies(docs.select("text")).where(f"n >= {max(2.0, how.least_share * n)} and n <= {how.most_share * n}")
        return cls(band.select("key").toArrow()["key"].to_numpy().view(np.uint64), how)

    def __getstate__(self):
        return {"how": self.how, "keys": self.keys}

    def hashes(self, column: pa.Array) -> np.ndarray:
        """documents x subsets; 0 for a subset without a term."""
        if not hasattr(self, "table"):
            self.table = KeyTable(self.keys)
        k = len(self.how.subsets)
        out = []
        for block in blocks(column):
            codes, first = terms(block)
            size = np.diff(first)
            doc = np.repeat(np.arange(block.n), size)
            known = self.table.find(codes) >= 0
            bare = np.bincount(doc, known, block.n) == 0
            use = known | bare[doc]
            codes, doc = codes[use], doc[use]
            got = np.zeros((block.n, k), np.uint64)
            for j, (part, seed) in enumerate(zip(self.how.subsets, seeds(k, 21), strict=True)):
                mixed = mix64(codes ^ seed)
                pick = np.flatnonzero(mixed <= np.uint64(min(part * 2.0**64, 2.0**64 - 2048)))
                if len(pick):
                    d = doc[pick]
                    at = np.flatnonzero(np.concatenate(([True], d[1:] != d[:-1])))
                    rank = (np.arange(len(d)) - np.repeat(at, np.diff(np.append(at, len(d))))).astype(np.uint64)
                    # hash of the sorted list: each term with its place
                    got[d[at], j] = np.add.reduceat(mix64(mixed[pick] + rank * np.uint64(0x9E3779B97F4A7C15)), at) | np.uint64(1)
            out.append(got)
        return np.concatenate(out)


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """By row of two arrays of hashes; 1 if neither has a field."""
    some = ((a > 0) | (b > 0)).sum(axis=1)
    return np.where(some > 0, ((a == b) & (a > 0)).sum(axis=1) / np.maximum(some, 1), 1.0)


def packed(hashes: np.ndarray) -> list[bytes]:
    """Four bytes a field, of the hash's upper half; zeros for a field without a term."""
    return [row.tobytes() for row in (hashes >> np.uint64(32)).astype(">u4")]


def fingerprints(docs: DataFrame, lexicon: Lexicon, text_column: str = "text") -> DataFrame:
    """docs with a column fingerprint, which replaces one of that name."""
    docs = docs.drop("fingerprint")
    shared, at = docs.sparkSession.sparkContext.broadcast(lexicon), docs.columns.index(text_column)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                made = pa.array([x.hex() for x in packed(shared.value.hashes(batch.column(at)))])
                yield pa.RecordBatch.from_arrays([*batch.columns, made], names=[*batch.schema.names, "fingerprint"])

    return docs.mapInArrow(run, T.StructType(list(docs.schema.fields)).add("fingerprint", "string"))


_PAIR = "doc_id bigint, n_chars bigint, edited_sha256 binary, fingerprint binary, edited_fingerprint binary, near_edited double, near_next double"
#: Rows of a partition that are worked on at once.
_ROWS = 256


def _pairs(ids: list, texts: list[str], following: list[str], lexicon: Lexicon) -> pa.RecordBatch:
    edited = [t[: len(t) - len(t) // 2] + f[: len(t) // 2] for t, f in zip(texts, following, strict=True)]
    a, b, c = (lexicon.hashes(pa.array(x, pa.large_string())) for x in (texts, edited, following))
    return pa.RecordBatch.from_arrays(
        [
            pa.array(ids, pa.int64()), pa.array([len(t) for t in texts], pa.int64()), pa.array([hashlib.sha256(t.encode()).digest() for t in edited]),
            pa.array(packed(a)), pa.array(packed(b)), pa.array(likeness(a, b)), pa.array(likeness(a, c)),
        ],
        names=["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
    )


def with_next(docs: DataFrame, lexicon: Lexicon, partitions: int) -> DataFrame:
    """Each text against its edited form (its last half of code points replaced by the next text's first ones)
    and the next text, in order of doc_id, the last followed by the first.

    Texts are dealt once, by ranges of doc_id; what a range lacks, the first text of the next one,
    comes from a table with two rows a range.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "imatch")
    shared = spark.sparkContext.broadcast(lexicon)

    def squeeze(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=1).compress
        for batch in batches:
            for lo in range(0, batch.num_rows, _ROWS):
                part = batch.slice(lo, _ROWS)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([pack((t or "").encode()) for t in part.column(1).to_pylist()], pa.binary())], names=["doc_id", "z"])

    # texts move once, squeezed; equal texts stay equal, so ties keep an order
    ranged = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInArrow(squeeze, "doc_id bigint, z binary")
    ranged = ranged.repartitionByRange(partitions, "doc_id").sortWithinPartitions("doc_id", "z").select(F.spark_partition_id().alias("part"), "doc_id", "z")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, ids, texts, opened, held = -1, [], [], False, 0

        def edge(first: bool) -> pa.RecordBatch:
            k = 0 if first else -1
            return pa.RecordBatch.from_arrays(
                [pa.array([part], pa.int32()), pa.array([first]), pa.array([ids[k]], pa.int64()), pa.array([texts[k]]), pa.nulls(1, pair)], names=["part", "first", "doc_id", "text", "pair"]
            )

        unpack = zstandard.ZstdDecompressor().decompress
        for batch in batches:
            for p, d, z in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                part, t = p, unpack(z).decode()
                ids.append(d)
                texts.append(t)
                held += len(t)
                if not opened:
                    yield edge(True)
                    opened = True
                if len(ids) > _ROWS or held > 1 << 20:
                    yield from done(part, ids, texts)
                    ids, texts, held = ids[-1:], texts[-1:], len(t)
        if opened:
            yield from done(part, ids, texts)
            yield edge(False)

    pair = pa.struct([("doc_id", pa.int64()), ("n_chars", pa.int64()), ("edited_sha256", pa.binary()), ("fingerprint", pa.binary()), ("edited_fingerprint", pa.binary()), ("near_edited", pa.float64()), ("near_next", pa.float64())])

    def done(part: int, ids: list, texts: list) -> Iterator[pa.RecordBatch]:
        """All but the last row, each with the one after it."""
        if len(ids) > 1:
            made = _pairs(ids[:-1], texts[:-1], texts[1:], shared.value)
            n = made.num_rows
            struct = pa.StructArray.from_arrays(made.columns, names=made.schema.names)
            yield pa.RecordBatch.from_arrays([pa.array([part] * n, pa.int32()), pa.nulls(n, pa.bool_()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.string()), struct], names=["part", "first", "doc_id", "text", "pair"])

    inner = scratch.save(ranged.mapInArrow(run, f"part int, first boolean, doc_id bigint, text string, pair struct<{_PAIR.replace(' bigint', ':bigint').replace(' binary', ':binary').replace(' double', ':double')}>"), "ranges")
    edges = inner.where("first is not null")
    heads = edges.where("first").select("part", F.col("text").alias("following"))
    # the first range at or after part + 1 that has rows, else the first of all
    order = heads.select("part").collect()
    parts = sorted(r["part"] for r in order)
    after = spark.createDataFrame([(p, parts[(i + 1) % len(parts)]) for i, p in enumerate(parts)], "part int, next int")
    lasts = edges.where("not first").select("part", "doc_id", "text").join(after, "part").join(heads.withColumnRenamed("part", "next"), "next")

    def close(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield _pairs(*(c.to_pylist() for c in batch.columns), shared.value)

    found = inner.where("first is null").select("pair.*").unionByName(lasts.select("doc_id", "text", "following").mapInArrow(close, _PAIR))
    return found.withColumns({c: F.lower(F.hex(c)) for c in ("edited_sha256", "fingerprint", "edited_fingerprint")})
