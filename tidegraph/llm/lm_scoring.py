"""Language-model scoring: a byte trie by partial matching, and a unigram base, over a whole corpus.

The trie (ppm.py) and the unigram counts are gathered from every training text: workers count keys
per partition, Spark adds the counts up. Neither has a bound, so neither is broadcast as a whole.

A byte string's code length needs the contexts that end like it only. So the strings of all texts are
dealt by the last bytes of their contexts (SPLIT of them); each share makes its part of the trie, with
the shorter contexts from whole counts of short strings (at most 256^SPLIT), and works out its strings'
lengths, equal to those of one trie of everything. The lengths of the strings used most, at most
max_strings, go to the workers; every occurrence of another string meets its length in a shuffle join.
The same holds for words: those above a count chosen so that at most hot_words remain are broadcast, the
occurrences of others joined. What is joined is summed in fixed point, so sums don't depend on order.

Cases: null texts score as empty ones (one closing token); null ids are neither held out nor
learnt from; repeated rows and ids each get their row; with no training text N and V are 0 and the
trie codes bytes uniformly; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tidegraph.llm.ppm import AdaptiveTrie, FrozenTrie, KeyTable, add_up, by_document, framed_keys, own_keys
from tidegraph.llm.textblocks import Block, blocks, spaced_words, word_codes
from tidegraph.plans.scratch import Scratch

#: The code of the token that closes each text.
END = np.uint64(0x9D39247E33776D41)
#: Fixed point of logarithms in sums, and of bits, which a long text has more of.
POINT = 1 << 40
BITS_POINT = 1 << 32
#: Bytes of context that deal the strings, and strings a share has on average at most.
SPLIT, SHARE = 3, 1 << 18

_WORD, _STRING, _UNLEARNT = 0, 1, 2


@dataclass(frozen=True)
class LmScoring:
    order: int = 5
    #: Strings and words that are broadcast; the others are joined.
    max_strings: int = 1 << 20
    hot_words: int = 1 << 18


def _counts(texts: DataFrame, order: int) -> DataFrame:
    """kind, key, n, uses over (text, learn), counted in each partition first.

    Words (with END) of the texts to learn from, and byte strings of all texts: n in those to learn from, uses in all.
    """

    def merge(held: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
        return add_up(np.concatenate([k for k, _ in held]), np.concatenate([c for _, c in held]))

    def out(kind: int, keys: np.ndarray, counts: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), kind, np.int8)), pa.array(keys.view(np.int64)), pa.array(counts)], names=["kind", "key", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {_WORD: [], _STRING: [], _UNLEARNT: []}
        for batch in batches:
            learnt = batch.column(0).filter(batch.column(1))
            held[_WORD].append((np.array([END]), np.array([len(learnt)])))
            for learn, column in ((True, learnt), (False, batch.column(0).filter(pc.invert(batch.column(1))))):
                for block in blocks(column):
                    strings = own_keys(block, order).astype(np.uint64)
                    found = {_WORD: word_codes(block, spaced_words(block)), _STRING: strings} if learn else {_UNLEARNT: strings}
                    for kind, keys in found.items():
                        held[kind].append(np.unique(keys, return_counts=True))
                        # bounds the worker's memory: many keys are merged, and given out if they stay many
                        if sum(len(k) for k, _ in held[kind]) > 1 << 20:
                            held[kind] = [merge(held[kind])]
                            if len(held[kind][0][0]) > 1 << 19:
                                yield out(kind, *held[kind].pop())
        for kind, parts in held.items():
            if parts:
                yield out(kind, *merge(parts))

    found = texts.mapInArrow(run, "kind tinyint, key bigint, n bigint")
    learnt = F.when(F.col("kind") == _UNLEARNT, 0).otherwise(F.col("n"))
    each = found.select(F.least("kind", F.lit(_STRING)).alias("kind"), "key", learnt.alias("n"), F.col("n").alias("uses"))
    return each.groupBy("kind", "key").agg(F.sum("n").alias("n"), F.sum("uses").alias("uses")).where((F.col("kind") == _STRING) | (F.col("n") > 0))


def _lengths(strings: DataFrame, order: int, partitions: int) -> DataFrame:
    """key, uses, bits: the code length of each string's last byte after the others, from the counts of all."""
    m = min(SPLIT, order)
    short = strings.where("n > 0").groupBy(F.col("key").bitwiseAND(F.lit((1 << 8 * m) - 1)).alias("key")).agg(F.sum("n").alias("n")).toArrow()
    below = strings.sparkSession.sparkContext.broadcast((m, short["key"].to_numpy().view(np.uint64), short["n"].to_numpy()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [tuple(c.to_numpy() for c in b.columns) for b in batches if b.num_rows]
        if parts:
            keys, n, uses = (np.concatenate(x) for x in zip(*parts, strict=True))
            del parts
            codes = keys.view(np.uint64)
            trie = FrozenTrie(codes[n > 0], n[n > 0], order, below.value)
            for lo in range(0, len(keys), 1 << 16):
                at = slice(lo, lo + (1 << 16))
                yield pa.RecordBatch.from_arrays([pa.array(keys[at]), pa.array(uses[at]), pa.array(trie.bits(codes[at]))], names=["key", "uses", "bits"])

    dealt = strings.select("key", "n", "uses").repartition(partitions, F.shiftrightunsigned("key", 8).bitwiseAND(F.lit((1 << 8 * m) - 1)))
    return dealt.mapInArrow(run, "key bigint, uses bigint, bits double")


def _least_count(counts: DataFrame, most: int, column: str = "n") -> int:
    """The least count c such that at most `most` keys have c or more."""
    total = 0
    for row in counts.groupBy(F.col(column).alias("n")).count().orderBy(F.desc("n")).toLocalIterator():
        total += row["count"]
        if total > most:
            return row["n"] + 1
    return 1


class Scorer:
    """What workers need: the hot strings with their code lengths, and the hot words with their logs."""

    def __init__(self, order: int, strings: np.ndarray, bits: np.ndarray, words: np.ndarray, logs: np.ndarray):
        self.order, self.strings, self.bits, self.words, self.logs = order, strings, bits, words, logs
        self._ready = False

    def __getstate__(self):
        return {k: getattr(self, k) for k in ("order", "strings", "bits", "words", "logs")} | {"_ready": False}

    def _prepare(self) -> None:
        if not self._ready:
            self.table = KeyTable(self.strings.astype(np.uint32 if self.order < 4 else np.uint64), room=2)
            self.padded = np.append(self.bits, 0.0)
            self.word_table = KeyTable(self.words)
            self._ready = True

    def score(self, block: Block):
        """Per text: tokens, hot tokens, their fixed-point logs, bits of hot strings; and the other tokens and strings, each with their numbers by text."""
        self._prepare()
        keys, first = framed_keys(block, self.order)
        at = self.table.find(keys)
        bits = by_document(self.padded[at], first, block.lengths)
        odd = np.flatnonzero(at < 0)
        of = np.searchsorted(first, odd, side="right") - 1
        own = odd <= first[of] + block.lengths[of]  # else a key of no document
        odd, of = keys[odd[own]].astype(np.uint64), of[own]
        words = spaced_words(block)
        codes = word_codes(block, words)
        # the closing token of each text stands after its words
        codes = np.insert(codes, words.first[1:], END)
        cut = words.first + np.arange(block.n + 1)
        hot = self.word_table.find(codes)
        logs = np.where(hot >= 0, self.logs[hot], 0) if len(self.logs) else np.zeros(len(codes), np.int64)
        cold = codes[hot < 0]
        counts = [np.add.reduceat(x, cut[:-1]) for x in ((hot >= 0).astype(np.int64), logs, (hot < 0).astype(np.int64))]
        return np.diff(cut), counts[0], counts[1], bits, cold, counts[2], odd, np.bincount(of, minlength=block.n)


def score(docs: DataFrame, learn: Column, how: LmScoring = LmScoring(), text_column: str = "text") -> DataFrame:
    """docs without the text, with n_tokens, n_known, train_tokens, base_score and score.

    learn: which rows of docs to gather statistics from.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "lm-scoring")
    learnt = docs.select(F.col(text_column).alias("text"), F.coalesce(learn, F.lit(False)).alias("learn"))
    counts = scratch.save(_counts(learnt, how.order), "counts")
    words, strings = counts.where(F.col("kind") == _WORD), counts.where(F.col("kind") == _STRING)
    n, v = words.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1))).first()
    least, hot = _least_count(strings, how.max_strings, "uses"), _least_count(words, how.hot_words)
    shares = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-strings.count() // SHARE))
    lengths = scratch.save(_lengths(strings, how.order, shares), "lengths")
    kept = lengths.where(F.col("uses") >= least).select("key", "bits").toArrow()
    common = words.where(F.col("n") >= hot).select("key", "n").toArrow()
    # logs of counts come from the same function on both ways
    logs = np.round(np.log10(common["n"].to_numpy() + 1.0) * POINT).astype(np.int64)
    scorer = Scorer(how.order, kept["key"].to_numpy().view(np.uint64), kept["bits"].to_numpy(), common["key"].to_numpy().view(np.uint64), logs)
    shared = spark.sparkContext.broadcast(scorer)

    results = ["n_tokens", "n_known", "train_tokens", "base_score", "score"]
    others = [f for f in docs.schema.fields if f.name != text_column and f.name not in results]
    fields = [F.col(f"`{f.name}`") for f in others]
    numbered = docs.select(F.monotonically_increasing_id().alias("row"), F.col(text_column).alias("text"), F.struct(*fields).alias("rest") if fields else F.lit(0).alias("rest"))

    def one(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            # a batch out for each block, so a worker holds the temporaries and results of one block only
            for block in blocks(batch.column(1)):
                tokens, known, logs, bits, cold, sizes, odd, odd_sizes = shared.value.score(block)
                lists = [pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(k))).astype(np.int32)), pa.array(x.view(np.int64))) for x, k in ((cold, sizes), (odd, odd_sizes))]
                rows = [batch.column(i).slice(block.first, block.n) for i in (0, 2)]
                yield pa.RecordBatch.from_arrays([*rows, *map(pa.array, (tokens, known, logs, bits)), *lists], names=["row", "rest", "tokens", "known", "logs", "bits", "cold", "odd"])

    schema = T.StructType([numbered.schema["row"], numbered.schema["rest"]])
    for name, kind in (("tokens", "long"), ("known", "long"), ("logs", "long"), ("bits", "double"), ("cold", T.ArrayType(T.LongType())), ("odd", T.ArrayType(T.LongType()))):
        schema = schema.add(name, kind)
    scored = scratch.save(numbered.mapInArrow(one, schema), "scored")

    rare = words.where(F.col("n") < hot).select("key", F.round(F.log10(F.col("n") + F.lit(1.0)) * POINT).cast("bigint").alias("log"))
    met = scored.select("row", F.explode("cold").alias("key")).join(rare, "key").groupBy("row").agg(F.count(F.lit(1)).alias("more"), F.sum("log").alias("more_logs"))
    odd = lengths.where(F.col("uses") < least).select("key", F.round(F.col("bits") * BITS_POINT).cast("bigint").alias("length"))
    coded = scored.select("row", F.explode("odd").alias("key")).join(odd, "key").groupBy("row").agg(F.sum("length").alias("more_bits"))
    out = scored.drop("cold", "odd").join(met, "row", "left").join(coded, "row", "left")
    total = (F.col("logs") + F.coalesce("more_logs", F.lit(0))) / F.lit(float(POINT))
    return out.select(
        *(F.col(f"rest.`{f.name}`").alias(f.name) for f in others),
        F.col("tokens").alias("n_tokens"),
        (F.col("known") + F.coalesce("more", F.lit(0))).alias("n_known"),
        F.lit(int(n)).cast("bigint").alias("train_tokens"),
        (total - F.col("tokens") * float(np.log10(n + v + 1))).alias("base_score"),
        ((F.col("bits") + F.coalesce("more_bits", F.lit(0)) / F.lit(float(BITS_POINT))) * float(-np.log10(2))).alias("score"),
    )


def adaptive_bits(text: str, order: int = 4, trie: AdaptiveTrie | None = None) -> float:
    """Code length of one text by a trie that learns as it reads, from nothing or from where trie stands."""
    return (trie or AdaptiveTrie(order)).code(text.encode())
