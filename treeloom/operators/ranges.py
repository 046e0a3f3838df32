"""Joins that Spark has no operator for: as-of joins and interval joins that stay linear on skewed keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, by: list[str], at: str, values: list[str], prefix: str = "asof_") -> DataFrame:
    """Each row of ``left`` with the ``values`` of the last row of ``right`` with the same key and an ``at`` not later.

    One union and one window: no row meets more than one other.  Ties on the right side go to the greatest values.
    """
    cols = left.columns
    a = left.withColumn("__v", F.lit(None).cast(right.select(F.struct(*values)).schema[0].dataType)).withColumn("__side", F.lit(1))
    b = right.select(*by, at, F.struct(*values).alias("__v")).withColumn("__side", F.lit(0))
    w = Window.partitionBy(*by).orderBy(at, "__side", F.col("__v").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True).withColumn("__last", F.last("__v", ignorenulls=True).over(w)).filter("__side = 1")
    return both.select(*cols, *[F.col(f"__last.{v}").alias(prefix + v) for v in values])


def point_in_interval(points: DataFrame, intervals: DataFrame, by: list[str], at: str, low: str, high: str, width: int) -> DataFrame:
    """Pairs of points and intervals of the same key with low <= at <= high.

    Both sides meet in bins of ``width``, so that one key's rows are spread over as many tasks as it has bins.
    """
    p = points.withColumn("__bin", F.floor(F.col(at) / width))
    i = intervals.withColumn("__bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return p.join(i, [*by, "__bin"]).filter(F.col(at).between(F.col(low), F.col(high))).drop("__bin")


def salted_join(left: DataFrame, right: DataFrame, on: str, salts: int = 16) -> DataFrame:
    """Inner join on a skewed key: the left side is dealt over ``salts`` partitions a key, the right side copied to each."""
    a = left.withColumn("__salt", F.pmod(F.xxhash64(*[F.col(f"`{c}`") for c in left.columns]), F.lit(salts)).cast("int"))
    b = right.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [on, "__salt"]).drop("__salt")


def broadcast_if_small(df: DataFrame, rows: int) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``rows`` rows; without one otherwise."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df
