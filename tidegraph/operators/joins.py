"""Joins that Spark has no operator for, as plans of those it has."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, values: list[str], tie: str | None = None) -> DataFrame:
    """left with the values of the last right row of its key at or before its time (null if none).

    Both sides are unioned and ordered once per key; no pair is made. Of equal times right rows come first;
    of several right rows at one time the last by tie counts.
    """
    t = F.col(tie) if tie else F.lit(0)
    a = left.select(F.struct("*").alias("l"), F.col(key).alias("k"), F.col(at).alias("t"), F.lit(1).alias("side"), F.lit(None).cast("bigint").alias("o"), F.lit(None).alias("v"))
    b = right.select(F.lit(None).alias("l"), F.col(key).alias("k"), F.col(at).alias("t"), F.lit(0).alias("side"), t.cast("bigint").alias("o"), F.struct(*values).alias("v"))
    w = Window.partitionBy("k").orderBy("t", "side", "o").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = a.unionByName(b).withColumn("v", F.last("v", ignorenulls=True).over(w)).where("side = 1")
    return both.select("l.*", *(F.col(f"v.{c}").alias(f"asof_{c}") for c in values))


def range_join(points: DataFrame, ranges: DataFrame, value: str, low: str, high: str, width: float) -> DataFrame:
    """Rows of points with the ranges [low, high) that hold their value: bins of a given width make it an equi-join.

    A range is repeated in each bin it touches, so width should be near a usual range's length.
    """
    b = lambda c: F.floor(c / F.lit(width)).cast("bigint")
    cut = ranges.withColumn("bin", F.explode(F.sequence(b(F.col(low)), b(F.col(high)))))
    return points.withColumn("bin", b(F.col(value))).join(cut, "bin").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("bin")


def salted_join(big: DataFrame, small: DataFrame, on: str, salts: int = 8) -> DataFrame:
    """An equi-join whose hot keys on the big side are dealt over several tasks; the small side is repeated for each salt."""
    a = big.withColumn("salt", F.pmod(F.xxhash64(*[F.col(c) for c in big.columns]), F.lit(salts)))
    b = small.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salts - 1).cast("bigint"))))
    return a.join(b, [on, "salt"]).drop("salt")
