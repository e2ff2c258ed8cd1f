"""Analyses of attributed items and of the index: who contains what, and from where."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provspark.operators.shared import cut
from provspark.sources.carriers import ATOMIC, TRAINING, role_of

UNKNOWN = "unknown"


def type_of(source: F.Column) -> F.Column:
    return F.when(source == UNKNOWN, UNKNOWN).otherwise(F.concat(F.lit("type"), (F.regexp_extract(source, r"(\d+)$", 1).cast("int") % 5).cast("string")))


def decompose(attributed: DataFrame, by: str = "source") -> DataFrame:
    """(dataset_id, origin, n, share) by source or by problem type; unattributed items are ``unknown``."""
    origin = F.coalesce("atomic_source", F.lit(UNKNOWN))
    origin = origin if by == "source" else type_of(origin)
    counts = attributed.groupBy("dataset_id", origin.alias("origin")).agg(F.count("*").alias("n"))
    return counts.withColumn("share", F.round(F.col("n") / F.sum("n").over(Window.partitionBy("dataset_id")), 6))


def decomposition_matrix(attributed: DataFrame, origins: list[str]) -> DataFrame:
    """Sets by sources; the values are given, so no extra pass finds them."""
    long = decompose(attributed)
    return long.groupBy("dataset_id").pivot("origin", origins).agg(F.sum("share")).na.fill(0.0)


def type_rollup(attributed: DataFrame) -> DataFrame:
    """Counts by (type, source) with subtotals by type and in all."""
    o = F.coalesce("atomic_source", F.lit(UNKNOWN))
    rows = attributed.select(type_of(o).alias("problem_type"), o.alias("origin"))
    return rows.rollup("problem_type", "origin").agg(F.count("*").alias("n"), F.grouping_id().cast("bigint").alias("level"))


def major_sources(attributed: DataFrame, min_share: float) -> DataFrame:
    """Sources with their size, rank within their type and whether they are major."""
    n = attributed.filter("atomic_source IS NOT NULL").groupBy("atomic_source").agg(F.count("*").alias("n"))
    n = n.withColumn("problem_type", type_of(F.col("atomic_source")))
    total = F.sum("n").over(Window.partitionBy())
    return n.withColumn("type_rank", F.dense_rank().over(Window.partitionBy("problem_type").orderBy(F.desc("n"))).cast("bigint")).withColumn("is_major", F.col("n") >= min_share * total)


def composition_distance(decomposition: DataFrame) -> DataFrame:
    """Total variation between the compositions of two sets: half the sum of absolute differences.

    Both sides have at most sets x sources rows.
    """
    a = decomposition.select(F.col("dataset_id").alias("a"), "origin", F.col("share").alias("p"))
    b = decomposition.select(F.col("dataset_id").alias("b"), "origin", F.col("share").alias("q"))
    shared = a.join(b, "origin").filter("a < b").groupBy("a", "b").agg(F.sum(F.least("p", "q")).alias("common"))
    sets = decomposition.select("dataset_id").distinct()
    pairs = sets.select(F.col("dataset_id").alias("a")).join(sets.select(F.col("dataset_id").alias("b")), F.col("a") < F.col("b"))
    return pairs.join(shared, ["a", "b"], "left").select("a", "b", F.round(1 - F.coalesce("common", F.lit(0.0)), 4).alias("distance"))


def first_introduction(attributed: DataFrame) -> DataFrame:
    """(atomic_source, dataset_id, released_at): the training set in which each source first shows up."""
    return attributed.filter("atomic_source IS NOT NULL").groupBy("atomic_source").agg(F.min(F.struct("released_at", "dataset_no", "dataset_id")).alias("f")).select("atomic_source", "f.dataset_id", "f.released_at")


def contribution_edges(states: DataFrame, mode: str = "first") -> DataFrame:
    """(parent, child, n) from one row a (key, set): parents by first, previous or every earlier set of a key."""
    order = ["released_at", "dataset_no"]
    if mode == "all":
        p = states.select("key", F.col("dataset_id").alias("parent"), F.struct(*order).alias("at_p"))
        c = states.select("key", F.col("dataset_id").alias("child"), F.struct(*order).alias("at_c"))
        return p.join(c, "key").filter("at_p < at_c").groupBy("parent", "child").agg(F.count("*").alias("n"))
    w = Window.partitionBy("key").orderBy(*order)
    parent = F.first("dataset_id").over(w) if mode == "first" else F.lag("dataset_id").over(w)
    return states.select(parent.alias("parent"), F.col("dataset_id").alias("child")).filter("parent IS NOT NULL AND parent <> child").groupBy("parent", "child").agg(F.count("*").alias("n"))


def overlap(states: DataFrame) -> DataFrame:
    """(a, b, inter, jaccard, cont_a, cont_b) of the key sets; within a key sets are distinct, so D^2 rows a key at most."""
    keys = states.select("key", "dataset_id").distinct()
    size = keys.groupBy("dataset_id").agg(F.count("*").alias("n"))
    a, b = (keys.select("key", F.col("dataset_id").alias(x)) for x in "ab")
    inter = a.join(b, "key").filter("a < b").groupBy("a", "b").agg(F.count("*").alias("inter"))
    out = inter.join(size.select(F.col("dataset_id").alias("a"), F.col("n").alias("na")), "a").join(size.select(F.col("dataset_id").alias("b"), F.col("n").alias("nb")), "b")
    return out.select("a", "b", "inter", F.round(F.col("inter") / (F.col("na") + F.col("nb") - F.col("inter")), 6).alias("jaccard"), F.round(F.col("inter") / F.col("na"), 6).alias("cont_a"), F.round(F.col("inter") / F.col("nb"), 6).alias("cont_b"))


def overlap_sketch(states: DataFrame) -> DataFrame:
    """(a, b, inter_estimate) from one theta sketch a set; keys are read once, pairs cost sketches only."""
    sketch = states.groupBy("dataset_id").agg(F.theta_sketch_agg("key").alias("s"))
    a, b = (sketch.select(F.col("dataset_id").alias(x), F.col("s").alias(f"s{x}")) for x in "ab")
    return a.join(b, F.col("a") < F.col("b")).select("a", "b", F.theta_sketch_estimate(F.theta_intersection("sa", "sb")).cast("bigint").alias("inter_estimate"))


def inheritance(states: DataFrame) -> DataFrame:
    """(introducer, heir, n): keys that a set introduced and another contains later."""
    w = Window.partitionBy("key").orderBy("released_at", "dataset_no")
    return states.withColumn("introducer", F.first("dataset_id").over(w)).filter("introducer <> dataset_id").groupBy("introducer", F.col("dataset_id").alias("heir")).agg(F.count("*").alias("n"))


def ancestry(edges: DataFrame) -> DataFrame:
    """(child, ancestor, depth): the least number of steps up, for chains of any length.

    Each round doubles the depth that is covered and keeps one row a pair, so rows never exceed D^2 for D sets and rounds are
    the logarithm of the longest chain; paths are never listed.
    """
    known = cut(edges.select("child", F.col("parent").alias("ancestor"), F.lit(1).cast("bigint").alias("depth")).filter("child <> ancestor").distinct(), "up")
    size: tuple | None = None
    while True:
        further = known.alias("x").join(known.alias("y"), F.col("x.ancestor") == F.col("y.child")).select("x.child", "y.ancestor", (F.col("x.depth") + F.col("y.depth")).alias("depth")).filter("child <> ancestor")
        known, before = cut(known.unionByName(further).groupBy("child", "ancestor").agg(F.min("depth").alias("depth")), "up"), size
        size = tuple(known.agg(F.count("*"), F.sum("depth")).first())
        if size == before:
            return known


def coverage(attributed: DataFrame) -> DataFrame:
    """Counts and shares by set and stage, with totals."""
    n = attributed.rollup("stage").agg(F.count("*").alias("n"))
    total = attributed.agg(F.count("*").alias("total"))
    return n.crossJoin(F.broadcast(total)).select(F.coalesce("stage", F.lit("all")).alias("stage"), "n", F.round(F.col("n") / F.col("total"), 6).alias("share"))


def novelty(states: DataFrame) -> DataFrame:
    """(dataset_id, new, total, share): keys that a set is the first to contain."""
    w = Window.partitionBy("key").orderBy("released_at", "dataset_no")
    return states.withColumn("rn", F.row_number().over(w)).groupBy("dataset_id").agg(F.count_if(F.col("rn") == 1).alias("new"), F.count("*").alias("total")).withColumn("share", F.round(F.col("new") / F.col("total"), 6))


def reuse_histogram(states: DataFrame) -> DataFrame:
    return states.groupBy("key").agg(F.count("*").alias("n_sets")).groupBy("n_sets").agg(F.count("*").alias("n_keys"))


def underused(attributed: DataFrame, max_sets: int) -> DataFrame:
    """Sources that few training sets contain."""
    return attributed.filter("atomic_source IS NOT NULL").groupBy("atomic_source").agg(F.count_distinct("dataset_id").alias("n_sets"), F.count("*").alias("n_items")).filter(F.col("n_sets") <= max_sets)


def core_upstreams(edges: DataFrame) -> DataFrame:
    """Parents by the children and items that they feed."""
    return edges.groupBy("parent").agg(F.count("*").alias("n_children"), F.sum("n").alias("n_items"))


def undeclared(edges: DataFrame, declared: DataFrame) -> DataFrame:
    """Edges that the child does not declare: declared has (parent, child)."""
    return edges.join(declared, ["parent", "child"], "left_anti")


def transparency(attributed: DataFrame, declared: DataFrame) -> DataFrame:
    """(dataset_id, declared_share, traced_share, gap): items whose traced source the set declares, and all traced."""
    d = declared.select(F.col("child").alias("dataset_id"), F.col("parent").alias("atomic_source"), F.lit(1).alias("said")).distinct()
    rows = attributed.join(d, ["dataset_id", "atomic_source"], "left")
    out = rows.groupBy("dataset_id").agg(F.avg(F.when(F.col("said") == 1, 1.0).otherwise(0.0)).alias("d"), F.avg(F.when(F.col("atomic_source").isNotNull(), 1.0).otherwise(0.0)).alias("t"))
    return out.select("dataset_id", F.round("d", 6).alias("declared_share"), F.round("t", 6).alias("traced_share"), F.round(F.col("t") - F.col("d"), 6).alias("gap"))


def redundancy(states: DataFrame) -> DataFrame:
    """Share of rows that a deduplicated collection would not need, by set and overall."""
    per = states.groupBy("dataset_id").agg(F.sum("n_items").alias("n"), F.count("*").alias("k"))
    every = states.groupBy("key").agg(F.sum("n_items").alias("n")).agg(F.lit("all").alias("dataset_id"), F.sum("n").alias("n"), F.count("*").alias("k"))
    return per.unionByName(every).select("dataset_id", F.col("n").alias("n_items"), F.col("k").alias("n_keys"), F.round(1 - F.col("k") / F.col("n"), 6).alias("redundancy"))


def training_only(df: DataFrame) -> DataFrame:
    return df.filter(role_of(F.col("dataset_no")) == TRAINING)


def atomic_only(df: DataFrame) -> DataFrame:
    return df.filter(role_of(F.col("dataset_no")) == ATOMIC)
