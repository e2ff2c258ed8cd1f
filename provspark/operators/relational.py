"""Joins and groupings that Spark lacks as operators: range, as-of, salted, gaps and islands."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(left: DataFrame, right: DataFrame, at: str, since: str, width: int) -> DataFrame:
    """Left rows with right rows whose ``since`` is within ``width`` seconds before ``at``.

    Both sides fall in bins of that width; a right row is sent to its bin and the next, so the join is an
    equi-join that shuffles by bin instead of a nested loop.
    """
    sec = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    w = width * 1_000_000
    a = left.withColumn("_t", sec(at)).withColumn("_bin", F.floor(F.col("_t") / w))
    b = right.withColumn("_s", sec(since)).withColumn("_bin", F.explode(F.array(F.floor(F.col("_s") / w), F.floor(F.col("_s") / w) + 1)))
    return a.join(b, "_bin").filter((F.col("_t") >= F.col("_s")) & (F.col("_t") <= F.col("_s") + w)).drop("_t", "_s", "_bin")


def asof_join(left: DataFrame, right: DataFrame, by: list[str], at: list[str], value: str, name: str) -> DataFrame:
    """Each left row with the last right ``value`` at or before it: one union and one window, no pairs.

    ``at`` orders both sides; right rows come first among equals.
    """
    a = left.withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).withColumn("_side", F.lit(1))
    cols = a.columns
    b = right.select(*[F.col(c) if c in by or c in at else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.col(value).alias("_v"), F.lit(0).alias("_side")).select(*cols)
    w = Window.partitionBy(*by).orderBy(*at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(name, F.last("_v", ignorenulls=True).over(w)).filter("_side = 1").drop("_v", "_side")


def salted_join(large: DataFrame, small: DataFrame, key: str, salts: int, salt: Column) -> DataFrame:
    """An equi-join in which each key of the large side is spread over ``salts`` tasks and the small side is repeated."""
    a = large.withColumn("_salt", F.pmod(salt, F.lit(salts)).cast("int"))
    b = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [key, "_salt"]).drop("_salt")


def sessions(events: DataFrame, by: str, at: str, order: list[str], gap_seconds: int) -> DataFrame:
    """Rows with ``session``, counted up by key where the gap to the row before is larger."""
    w = Window.partitionBy(by).orderBy(*order)
    new = F.when(F.unix_micros(F.col(at).cast("timestamp")) - F.lag(F.unix_micros(F.col(at).cast("timestamp"))).over(w) > gap_seconds * 1_000_000, 1).otherwise(0)
    return events.withColumn("_new", new).withColumn("session", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0))).drop("_new")


def salted_count(df: DataFrame, key: str, salts: int, salt: Column) -> DataFrame:
    """Counts in two steps, so a hot key is first summed in parts."""
    return df.groupBy(key, F.pmod(salt, F.lit(salts)).alias("_salt")).agg(F.count("*").alias("n")).groupBy(key).agg(F.sum("n").alias("n"))
