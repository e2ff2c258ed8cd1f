"""Connected components of an edge table by alternating star contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provspark.llm.common import Scratch, drop_table, write_read


def connected_components(edges: DataFrame, tmp: Scratch, a: str = "a", b: str = "b") -> DataFrame:
    """Rows (id, component): the least id reachable, for each id of an edge other than that least one.

    Each round links every node's larger neighbours to its least one, then its smaller ones; the
    edge table never grows, and rounds go on until all that is left are stars.  Least neighbours come from partial aggregates, so a node with very
    many edges costs one row a task.  Each round is written, so lost executors cost one round.
    """
    now = write_read(edges.filter(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct(), "edges")
    while True:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.unionByName(least.filter("m < u").select("u", F.col("m").alias("v"))).distinct()
        large = write_read(large, "large")
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u")
        small = small.select("u", F.col("m").alias("v")).unionByName(small.filter("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))).distinct()
        after = write_read(small, "small")
        drop_table(large)
        drop_table(now)
        now = after
        stars = now.groupBy("u").count().filter("count > 1").limit(1).count() == 0 and now.select("v").join(now.select(F.col("u").alias("v")), "v", "left_semi").limit(1).count() == 0
        if stars:
            break
    tmp.tables.append(now)
    return now.select(F.col("u").alias("id"), F.col("v").alias("component"))
