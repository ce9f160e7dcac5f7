"""Joins that Spark has no operator for: by range, by time, by nearest earlier row."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(left: DataFrame, right: DataFrame, value: str, low: str, high: str, width: float) -> DataFrame:
    """Rows of ``left`` with those of ``right`` whose interval [low, high] holds their value.

    Both sides are dealt to bins of ``width``; an interval goes to every bin that
    it touches, so each pair meets exactly once, in the bin of the value.
    """
    of = lambda c: F.floor(F.col(c) / F.lit(width))
    binned = right.withColumn("_bin", F.explode(F.sequence(of(low), of(high))))
    return left.withColumn("_bin", of(value)).join(binned, "_bin").where(F.col(value).between(F.col(low), F.col(high))).drop("_bin")


def asof_join(left: DataFrame, right: DataFrame, by: list[str], time: str, right_time: str, carry: list[str], ties: list[str]) -> DataFrame:
    """Each row of ``left`` with the columns ``carry`` of the last row of ``right`` at or before its time, per group.

    Both sides are merged into one ordered stream, so a group needs one sort and
    no pairing. ``ties`` orders rows of ``right`` with equal times.
    """
    fields = F.struct(*carry)
    l = left.withColumn("_t", F.col(time)).withColumn("_side", F.lit(1)).withColumn("_right", F.lit(None).cast(right.select(fields).schema[0].dataType))
    r = right.select(*by, F.col(right_time).alias("_t"), F.lit(0).alias("_side"), fields.alias("_right"), *[F.col(c).alias(f"_tie{i}") for i, c in enumerate(ties)])
    order = Window.partitionBy(*by).orderBy("_t", "_side", *[f"_tie{i}" for i in range(len(ties))])
    merged = l.unionByName(r, allowMissingColumns=True).withColumn("_last", F.last("_right", ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return merged.where("_side = 1").select(*left.columns, *[F.col("_last")[c].alias(c) for c in carry])


def interval_join(left: DataFrame, right: DataFrame, by: list[str], left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of one group at most ``seconds`` apart; times are dealt to buckets of that length and meet in the same or a neighbouring one."""
    micros = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    at = lambda c: F.floor(micros(c) / F.lit(seconds * 1_000_000))
    r = right.withColumn("_b", F.explode(F.array(at(right_time) - 1, at(right_time), at(right_time) + 1)))
    near = F.abs(micros(left_time) - micros(right_time)) <= F.lit(seconds * 1_000_000)
    return left.withColumn("_b", at(left_time)).join(r, [*by, "_b"]).where(near).drop("_b")


def reach_semi(df: DataFrame, column: str, pairs: DataFrame, end: str = "x", *, anti: bool = False) -> DataFrame:
    """Rows whose column has (or, with ``anti``, has not) a partner among reachable pairs."""
    return df.join(pairs.select(F.col(end).alias(column)).distinct(), column, "left_anti" if anti else "left_semi")


def cosine(x: Column, y: Column) -> Column:
    """Cosine of two arrays of doubles."""
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda t, p: t + p)
    return dot(x, y) / F.sqrt(dot(x, x) * dot(y, y))
