"""Mixing sources to target weights by temperature, as budgeted block permutations.

Token shares p of the sources are raised to an exponent and normalised: w = p^a / sum p^a. Lower
exponents flatten the mixture: its entropy grows, and so does the largest repetition of a source,
budget * w / tokens. The exponent is the largest in [0, 1] whose entropy reaches target_entropy
times the logarithm of the number of sources, raised again as far as the repetition limit asks. It
is found by repeated division of the interval, each pass one aggregate over the sources for all
trial exponents of the pass.

A source's weight becomes a quota of tokens. Its documents are laid out in epochs, each a new
permutation (by a hash of seed, epoch and id); whole epochs are followed by the start of one more, as
far as documents fit the quota. The mixture is cut into blocks of about block_tokens, and an
occurrence goes to the block where its source's running share of quota falls, so every block holds
each source in its weight; `place` is a pseudo-random order within the block.

Only DataFrame functions are used. Running sums are taken in two levels, within buckets of the hash
and over the buckets' totals, so a source with a third of all rows is never sorted in one task.

Cases: a null source is a source of its own; null texts have no tokens; sources without tokens get
no quota, and their documents are left out; elsewhere documents without tokens stand where their
hash puts them; a null id hashes as an empty one; repeated rows are each documents; ties of the hash
are ordered by id and tokens; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from tidegraph.plans.scratch import Scratch

#: Words are runs of other bytes than these.
_WORD = r"[^\x20\x09-\x0D]+"
#: Trial exponents of a pass, and passes: steps of 32^-5.
_STEPS, _PASSES = 32, 5
_TINY = 1e-12


@dataclass(frozen=True)
class Mixing:
    target_entropy: float = 0.95
    most_repeats: float = 4.0
    budget_share: float = 1.0  # of all tokens
    block_tokens: int = 65536
    bucket_rows: int = 1024
    seed: int = 42


def tokens(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(_WORD)), F.lit(0)).cast("bigint")


def _key(source: Column) -> Column:
    return F.when(source.isNull(), F.lit("-")).otherwise(F.concat(F.lit("="), source.cast("string")))


def exponent(sources: DataFrame, total: int, count: int, how: Mixing) -> float:
    """sources: t (tokens above 0) for each of `count` sources with `total` tokens."""
    wanted = how.target_entropy * _log(count)
    trials = sources.select(F.log(F.col("t") / F.lit(float(total))).alias("p"))

    def search(enough) -> float:
        """The largest exponent for which enough holds; it holds at 0 and below some exponent."""
        lo, hi = 0.0, 1.0
        for i in range(_PASSES):
            step = (hi - lo) / _STEPS
            grid = trials.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(_STEPS)))).withColumn("a", F.lit(lo) + F.col("i") * F.lit(step))
            e = F.exp(F.col("a") * F.col("p"))
            rows = grid.groupBy("i").agg(F.sum(e).alias("z"), F.sum(e * F.col("a") * F.col("p")).alias("m"), F.max(F.exp((F.col("a") - 1) * F.col("p"))).alias("r")).collect()
            held = max((r["i"] for r in rows if enough(r)), default=0)
            if held == _STEPS:
                return hi
            lo, hi = lo + held * step, lo + (held + 1) * step
        return lo

    # entropy: log z - (sum e * a * p) / z; largest repetition: budget_share * max p^(a-1) / z
    by_entropy = search(lambda r: _log(r["z"]) - r["m"] / r["z"] >= wanted - _TINY)
    if how.most_repeats <= how.budget_share:
        return 1.0
    # repetition falls as the exponent grows: the largest exponent still above the limit, and one step more
    over = search(lambda r: how.budget_share * r["r"] / r["z"] > how.most_repeats)
    return max(by_entropy, over + _STEPS**-_PASSES if over > 0 else 0.0)


def _log(x: float) -> float:
    from math import log

    return log(x)


def mix(docs: DataFrame, how: Mixing = Mixing(), id_column: str = "doc_id", source_column: str = "source", text_column: str = "text", payload: list[str] | None = None) -> DataFrame:
    """A row for each occurrence: the payload columns as a struct `row`, source, n_tokens, epoch, block, place."""
    scratch = Scratch(docs.sparkSession, "mixing")
    payload = [id_column] if payload is None else payload
    held = docs.select(
        F.struct(*(F.col(f"`{c}`") for c in payload)).alias("row"), F.col(id_column).cast("string").alias("id"), F.col(source_column).alias("source"),
        _key(F.col(source_column)).alias("key"), tokens(F.col(text_column)).alias("n_tokens"),
    )
    if text_column not in payload:
        held = scratch.save(held, "rows")
    sources = scratch.save(held.groupBy("key").agg(F.sum("n_tokens").alias("t"), F.count(F.lit(1)).alias("n")).where("t > 0"), "sources")
    total, count = sources.agg(F.coalesce(F.sum("t"), F.lit(0)), F.count(F.lit(1))).first()
    a = exponent(sources, total, count, how) if count else 1.0
    raised = F.exp(F.lit(a) * F.log(F.col("t") / F.lit(float(max(total, 1)))))
    z = sources.agg(F.coalesce(F.sum(raised), F.lit(1.0))).first()[0]
    budget = int(how.budget_share * total)
    # rounding must not cost a whole quota its last token
    quota = F.floor(raised / F.lit(z) * F.lit(float(budget)) + F.lit(1e-6)).cast("bigint")
    # buckets of a source: a power of two, so that hash buckets nest
    bits = F.greatest(F.lit(0), F.ceil(F.log2(F.col("n") / F.lit(float(how.bucket_rows))))).cast("int")
    plan = sources.select("key", "t", quota.alias("quota"), bits.alias("bits")).where("quota > 0")
    blocks = max(1, -(-budget // how.block_tokens))

    hashed = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(how.seed)), F.col("epoch").cast("string"), F.coalesce("id", F.lit("")))), 1, 15), 16, 10).cast("bigint")
    laid = (
        held.join(plan, "key")
        .withColumn("epoch", F.explode(F.sequence(F.lit(0), F.expr("cast(quota div t as int)"))))
        .where("epoch * t < quota")
        .withColumn("h", hashed)
        .withColumn("bucket", F.expr("shiftright(h, 60 - bits)"))
    )
    totals = laid.groupBy("key", "epoch", "bucket").agg(F.sum("n_tokens").alias("s"))
    over = Window.partitionBy("key", "epoch").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    before = totals.select("key", "epoch", "bucket", F.coalesce(F.sum("s").over(over), F.lit(0)).alias("base"))
    inner = Window.partitionBy("key", "epoch", "bucket").orderBy("h", "id", "n_tokens").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    summed = laid.withColumn("within", F.sum("n_tokens").over(inner)).join(before, ["key", "epoch", "bucket"])
    # tokens of the source up to and with this occurrence, all epochs counted
    upto = summed.withColumn("upto", F.expr("epoch * t + base + within")).where("upto <= quota")
    block = F.expr(f"cast(least({blocks - 1}, floor((upto - n_tokens) / quota * {float(blocks)}D)) as bigint)")
    return upto.select("row", "source", "n_tokens", "epoch", block.alias("block"), F.conv(F.substring(F.md5(F.concat(F.lit("place:"), F.col("h").cast("string"))), 1, 15), 16, 10).cast("bigint").alias("place"))
