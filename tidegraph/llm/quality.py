"""Quality classifier: logistic regression over hashed word n-grams, trained with FTRL-proximal.

Tokens are runs of letters and digits (A-Z lowered, bytes from 0x80 on counted as letters) and runs
of other visible characters. Each unigram and bigram falls into one of 2^bits coordinates (a word and its repetition into the same one); a text's
vector holds each coordinate's share of its n-grams, times a constant, so length alone moves
nothing, and the score is a sparse dot product: the mean of the coordinates' weights.

Training takes about train_rows labelled documents at most, chosen by a hash of the id over all,
each with its whole text, and fewer of them by another hash where they hold more than train_bytes of text.

Cases: null and blank texts get the intercept's score; with no labelled row, or one class only,
scores lean to the prior (0.5 with no row); null ids and repeated rows are scored as they are; an
empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tidegraph.llm.common import bounded_rows, per_batch
from tidegraph.llm.textblocks import Block, blocks, prefix_code, range_code, runs, LOWER, sums

_CLASS = np.full(256, 2, np.uint8)  # other visible characters
_CLASS[:33] = 0
_CLASS[127] = 0
_CLASS[48:58] = _CLASS[65:91] = _CLASS[97:123] = _CLASS[128:] = 1

#: The code of any word followed by itself: all such bigrams share one coordinate.
_REPEAT = np.uint64(0xD1B54A32D192ED03)


@dataclass(frozen=True)
class Quality:
    bits: int = 18
    train_rows: int = 4000
    train_bytes: int = 64 << 20
    epochs: int = 4
    alpha: float = 0.5
    beta: float = 1.0
    l1: float = 0.02
    l2: float = 0.5
    scale: float = 16.0


def ngrams(block: Block, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Coordinates of all unigrams and bigrams, and offsets by document."""
    kind = _CLASS[block.data]
    both = [runs(block, kind == k) for k in (1, 2)]
    start = np.concatenate([w.start for w in both])
    order = np.argsort(start, kind="stable")
    start, end = start[order], np.concatenate([w.end for w in both])[order]
    first = both[0].first + both[1].first
    one = range_code(prefix_code(LOWER[block.data]), start, end)
    inner = np.ones(len(one), bool)
    ends = first[1:] - 1
    inner[ends[np.diff(first) > 0]] = False
    two = (one[:-1] * np.uint64(3) + one[1:] * np.uint64(0x9E3779B97F4A7C15)) if len(one) else one
    two[one[:-1] == one[1:]] = _REPEAT
    shift = np.uint64(64 - bits)
    out = np.empty(2 * len(one) - (np.diff(first) > 0).sum(), np.int32)
    place = np.arange(len(one)) + np.concatenate(([0], np.cumsum(inner)[:-1])) if len(one) else np.zeros(0, np.int64)
    out[place] = (one >> shift).astype(np.int32)
    at = np.flatnonzero(inner)
    out[place[at] + 1] = (two[at] >> shift).astype(np.int32)
    before = np.concatenate(([0], np.cumsum(inner)))
    return out, first + before[first]


class QualityModel:
    def __init__(self, how: Quality):
        self.how = how
        self.weights = np.zeros(1 << how.bits, np.float32)
        self.intercept = 0.0

    def fit(self, rows: list[tuple[np.ndarray, np.ndarray, int]]) -> QualityModel:
        """rows: distinct coordinates, their counts, label."""
        h = self.how
        z, n = np.zeros(1 << h.bits), np.zeros(1 << h.bits)
        z0 = n0 = 0.0
        for epoch in range(h.epochs):
            for at in np.random.default_rng(epoch).permutation(len(rows)):
                ids, counts, label = rows[at]
                x = counts * (h.scale / max(counts.sum(), 1))
                zi, ni = z[ids], n[ids]
                w = np.where(np.abs(zi) <= h.l1, 0.0, -(zi - np.sign(zi) * h.l1) / ((h.beta + np.sqrt(ni)) / h.alpha + h.l2))
                w0 = -z0 / ((h.beta + np.sqrt(n0)) / h.alpha)
                p = 1 / (1 + np.exp(-np.clip(w0 + w @ x, -35, 35)))
                g, g0 = (p - label) * x, p - label
                z[ids] += g - (np.sqrt(ni + g * g) - np.sqrt(ni)) / h.alpha * w
                n[ids] += g * g
                z0 += g0 - (np.sqrt(n0 + g0 * g0) - np.sqrt(n0)) / h.alpha * w0
                n0 += g0 * g0
        self.weights = np.where(np.abs(z) <= h.l1, 0.0, -(z - np.sign(z) * h.l1) / ((h.beta + np.sqrt(n)) / h.alpha + h.l2)).astype(np.float32)
        self.intercept = float(-z0 / ((h.beta + np.sqrt(n0)) / h.alpha))
        return self

    def score(self, column: pa.Array) -> np.ndarray:
        out = []
        for block in blocks(column):
            ids, first = ngrams(block, self.how.bits)
            mean = sums(self.weights[ids], first) / np.maximum(np.diff(first), 1)
            out.append(1 / (1 + np.exp(-np.clip(self.intercept + self.how.scale * mean, -35, 35))))
        return np.concatenate(out)


def fit(docs: DataFrame, labels: DataFrame, how: Quality = Quality()) -> QualityModel:
    """docs: doc_id, text; labels: doc_id, label (0 or 1; others are left out)."""
    chosen = bounded_rows(labels.where("doc_id is not null and label in (0, 1)"), "doc_id", how.train_rows)

    def one(batch: pa.RecordBatch) -> pa.RecordBatch:
        ids, counts, sizes = [], [], []
        for block in blocks(batch.column(1)):
            got, first = ngrams(block, how.bits)
            for i in range(block.n):
                u, c = np.unique(got[first[i] : first[i + 1]], return_counts=True)
                ids.append(u)
                counts.append(c.astype(np.int32))
                sizes.append(len(u))
        at = pa.array(np.concatenate(([0], np.cumsum(sizes))).astype(np.int32))
        lists = [pa.ListArray.from_arrays(at, pa.array(np.concatenate(x))) for x in (ids, counts)]
        return pa.RecordBatch.from_arrays([batch.column(0), *lists, batch.column(2)], names=["doc_id", "ids", "counts", "label"])

    rows = docs.select("doc_id", "text").join(F.broadcast(chosen.select("doc_id", "label")), "doc_id").select("doc_id", "text", "label")
    long = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    if long > how.train_bytes:
        rows = rows.where(F.pmod(F.xxhash64("doc_id", F.lit(41)), F.lit(1 << 30)) < int((1 << 30) * how.train_bytes / long))
    got = per_batch(rows, one, "doc_id bigint, ids array<int>, counts array<int>, label int").toArrow().sort_by([("doc_id", "ascending"), ("label", "ascending")])
    ids, counts = got["ids"].combine_chunks(), got["counts"].combine_chunks()
    data = [(i.values.to_numpy(), c.values.to_numpy(), y) for i, c, y in zip(ids, counts, got["label"].to_pylist(), strict=True)]
    return QualityModel(how).fit(data)


def score(docs: DataFrame, model: QualityModel, text_column: str = "text") -> DataFrame:
    """docs with score in place of the text column; a column of that name is replaced."""
    docs = docs.drop("score")
    shared = docs.sparkSession.sparkContext.broadcast(model)
    text = docs.columns.index(text_column)
    kept = [i for i in range(len(docs.columns)) if i != text]

    def one(batch: pa.RecordBatch) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([*(batch.column(i) for i in kept), pa.array(shared.value.score(batch.column(text)))], names=[*(docs_names[i] for i in kept), "score"])

    docs_names = docs.columns
    return per_batch(docs, one, T.StructType([docs.schema.fields[i] for i in kept]).add("score", "double"))
