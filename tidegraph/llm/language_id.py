"""Language identification by code length: one frozen byte trie (ppm.py) per language.

Texts are folded to letters first: A-Z to lower case, any other ASCII byte to a space; other bytes
stay. A text's language is the one whose trie codes it in the fewest bits; the score is that
language's share when code lengths are read as probabilities with equal priors.

The tries are fitted on a bounded number of documents per language (rows_per_language, about that
many, chosen by a hash of the id over all of them), each with its whole text. Every code length the
tries assign to a key seen in training is worked out once for all languages, so scoring is one
lookup a byte; the other keys go through the tries.

Cases: null texts and texts without a letter are "und" with score 0; with no learned language every
text is "und"; ties go to the first language in order; null and repeated ids are kept as they are;
an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tidegraph.llm.common import per_batch
from tidegraph.llm.ppm import FrozenTrie, KeyTable, add_up, by_document, framed_keys, own_keys
from tidegraph.llm.textblocks import blocks, sums

UNDETERMINED = "und"

FOLD = np.arange(256, dtype=np.uint8)
FOLD[:128] = 32
FOLD[97:123] = np.arange(97, 123)
FOLD[65:91] = np.arange(97, 123)

_LETTER = np.zeros(256, bool)
_LETTER[65:91] = _LETTER[97:123] = True


@dataclass(frozen=True)
class LanguageId:
    order: int = 3
    rows_per_language: int = 2000


class LanguageModel:
    """Frozen tries of all languages, with their code lengths side by side."""

    def __init__(self, languages: list[str], counts: dict[str, tuple[np.ndarray, np.ndarray]], order: int):
        self.languages, self.order = languages, order
        self.tries = [FrozenTrie(*counts[x], order) for x in languages]
        kind = np.uint32 if order < 4 else np.uint64
        known = np.unique(np.concatenate([counts[x][0] for x in languages] or [np.zeros(0, kind)])).astype(kind)
        self.table = KeyTable(known)
        # one row more, for keys that no language has seen
        self.bits = [np.append(t.bits(known), 0.0).astype(np.float32) for t in self.tries]

    def score(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Language numbers (-1: undetermined) and scores."""
        best, score = [], []
        for block in blocks(column):
            keys, first = framed_keys(block, self.order, FOLD)
            at = self.table.find(keys)
            odd = np.flatnonzero(at < 0)
            rare, back = np.unique(keys[odd], return_inverse=True)
            rows = []
            for bits, trie in zip(self.bits, self.tries, strict=True):
                each = bits[at]
                each[odd] = trie.bits(rare)[back]
                rows.append(by_document(each, first, block.lengths))
            if rows:
                total = np.array(rows)
                low = total.argmin(axis=0)
                with np.errstate(under="ignore"):
                    share = 1 / np.exp2(np.maximum(total.min(axis=0) - total, -1000)).sum(axis=0)
            else:
                low, share = np.full(block.n, -1), np.zeros(block.n)
            spoken = sums(_LETTER[block.data], block.offsets) > 0
            for i in np.flatnonzero(~spoken):  # other letters are looked for where ASCII has none
                text = bytes(block.data[block.offsets[i] : block.offsets[i + 1]]).decode("utf-8", "replace")
                spoken[i] = any(c.isalpha() for c in text)
            best.append(np.where(spoken, low, -1))
            score.append(np.where(spoken, share, 0.0))
        return np.concatenate(best), np.concatenate(score)


def _key_counts(docs: DataFrame, order: int) -> DataFrame:
    """lang, key, n over the texts; counted in each batch first."""

    def one(batch: pa.RecordBatch) -> pa.RecordBatch | None:
        out = []
        for lang in batch.column(1).unique():
            rows = batch.filter(pc.equal(batch.column(1), lang))
            parts = [np.unique(own_keys(b, order, FOLD), return_counts=True) for b in blocks(rows.column(0), 8 << 20)]
            keys, counts = add_up(np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts]))
            out.append((np.repeat(lang.as_py(), len(keys)), keys.astype(np.int64), counts))
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate([x[i] for x in out])) for i in range(3)], names=["lang", "key", "n"])

    return per_batch(docs.select("text", "lang"), one, "lang string, key bigint, n bigint").groupBy("lang", "key").agg(F.sum("n").alias("n"))


def fit(docs: DataFrame, learn: Column, how: LanguageId = LanguageId()) -> LanguageModel:
    """Learns from the rows of docs (doc_id, text, lang) for which learn is true and neither of the three is null."""
    rows = docs.where(learn & F.col("doc_id").isNotNull() & F.col("lang").isNotNull() & F.col("text").isNotNull())
    share = {r["lang"]: how.rows_per_language / r["count"] for r in rows.groupBy("lang").count().collect()}
    drawn = F.pmod(F.xxhash64(F.col("doc_id"), F.lit(20)), F.lit(1 << 20)) / (1 << 20)
    if any(s < 1 for s in share.values()):
        few = F.create_map(*[x for lang, s in share.items() for x in (F.lit(lang), F.lit(s))])
        rows = rows.where(drawn < few[F.col("lang")])
    got = _key_counts(rows, how.order).toArrow() if share else None
    counts, kind = {}, np.uint32 if how.order < 4 else np.uint64
    for lang in sorted(share):
        mine = got.filter(pc.equal(got["lang"], lang))
        if mine.num_rows:
            counts[lang] = (mine["key"].to_numpy().astype(kind), mine["n"].to_numpy())
    return LanguageModel(sorted(counts), counts, how.order)


def identify(docs: DataFrame, model: LanguageModel, text_column: str = "text") -> DataFrame:
    """docs with lang_pred and score, which replace columns of these names."""
    docs = docs.drop("lang_pred", "score")
    shared = docs.sparkSession.sparkContext.broadcast(model)
    fields = docs.columns
    text = fields.index(text_column)

    def one(batch: pa.RecordBatch) -> pa.RecordBatch:
        best, score = shared.value.score(batch.column(text))
        names = np.array([*shared.value.languages, UNDETERMINED], dtype=object)
        return pa.RecordBatch.from_arrays([*batch.columns, pa.array(names[best], pa.string()), pa.array(score)], names=[*fields, "lang_pred", "score"])

    return per_batch(docs, one, T.StructType(list(docs.schema.fields)).add("lang_pred", "string").add("score", "double"))
