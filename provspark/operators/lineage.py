"""Lineage: key index in release order, exact attribution, increments, unmatched items.

"First" is the least (released_at, dataset_no, seq).  The chronological walk over all items is a
commutative aggregate here: the order comes from the data, so partial states merge in any order.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from provspark.config import INSPECTED, SEED
from provspark.functions.keys import content_key, join_key, seeded
from provspark.sources.carriers import AGGREGATE, ATOMIC, TRAINING, role_of

ORDER = ["released_at", "dataset_no", "seq"]


def keyed(items: DataFrame, level: str = "raw") -> DataFrame:
    """Items with ``key``, 20 bytes."""
    return items.withColumn("key", join_key(F.col("prompt"), level))


def first_of(*fields: str) -> Column:
    return F.min(F.struct(*ORDER, *[f for f in fields if f not in ORDER]))


def set_states(keyed_items: DataFrame, *extra: Column) -> DataFrame:
    """One row a (key, set): counts, the set's first item, extra aggregates.  A set's own copies vanish before any wide shuffle."""
    return keyed_items.filter("key IS NOT NULL").groupBy("key", "dataset_id", "dataset_no", "released_at").agg(F.count("*").alias("n_items"), F.min(F.struct("seq", "item_id")).alias("first_item"), *extra)


def build_index(items: DataFrame, level: str = "raw") -> DataFrame:
    """The lineage dictionary: (key, n_items, n_sets, first, occurrences, meta).

    ``occurrences`` holds every set of a key in release order: one entry a set, never one an item.
    """
    states = set_states(keyed(items, level), F.min_by("meta", F.col("seq")).alias("meta"))
    entry = F.struct("released_at", "dataset_no", F.col("first_item.seq").alias("seq"), "dataset_id", F.col("first_item.item_id").alias("item_id"))
    return states.groupBy("key").agg(
        F.sum("n_items").alias("n_items"),
        F.count("*").alias("n_sets"),
        F.min(entry).alias("first"),
        F.array_sort(F.collect_list(entry)).alias("occurrences"),
        F.min_by("meta", F.struct("released_at", "dataset_no")).alias("meta"),
    )


def long_index(items: DataFrame, level: str = "raw") -> DataFrame:
    """Mergeable form: one row a (key, set), so adding a set touches its own rows only."""
    return set_states(keyed(items, level)).select("key", "dataset_id", "dataset_no", "released_at", "n_items", F.col("first_item.seq").alias("seq"), F.col("first_item.item_id").alias("item_id"))


def append_to_index(index: DataFrame, items: DataFrame, level: str = "raw") -> DataFrame:
    """A long index with more items, whatever their dates; equal to building from all items at once."""
    both = index.unionByName(long_index(items, level))
    return both.groupBy("key", "dataset_id", "dataset_no", "released_at").agg(F.sum("n_items").alias("n_items"), F.min(F.struct("seq", "item_id")).alias("f")).select("key", "dataset_id", "dataset_no", "released_at", "n_items", "f.seq", "f.item_id")


def occurrence_status(items: DataFrame, level: str = "raw") -> DataFrame:
    """Each item as first, repeat (a later set) or duplicate (again in its own set)."""
    of_key = Window.partitionBy("key").orderBy(*ORDER)
    in_set = Window.partitionBy("key", "dataset_id").orderBy("seq")
    rows = keyed(items, level).withColumn("rn", F.row_number().over(of_key)).withColumn("in_set", F.row_number().over(in_set))
    return rows.withColumn("status", F.when(F.col("key").isNull(), "unknown").when(F.col("rn") == 1, "first").when(F.col("in_set") > 1, "duplicate").otherwise("repeat"))


def merge_metadata(items: DataFrame, policy: str = "earliest", level: str = "raw") -> DataFrame:
    """(key, answer, lang): the first or last metadata provided for a key; items without any do not overwrite."""
    pick = F.min_by if policy == "earliest" else F.max_by
    order = F.struct(*ORDER)
    value = lambda c: pick(c, F.when(c.isNotNull(), order))
    return keyed(items, level).filter("key IS NOT NULL").groupBy("key").agg(value(F.col("answer")).alias("answer"), value(F.col("meta")["lang"]).alias("lang"))


def lookup(index: DataFrame, probes: DataFrame, prompt: str = "prompt", level: str = "raw") -> DataFrame:
    """Probes with what the index knows of them; an equi-join that Spark sizes."""
    known = index.select("key", F.col("first.dataset_id").alias("first_dataset"), F.col("first.item_id").alias("first_item"), "n_items", "n_sets")
    return probes.withColumn("key", join_key(F.col(prompt), level)).join(known, "key", "left").withColumn("known", F.col("n_items").isNotNull())


def origins(states: DataFrame) -> DataFrame:
    """(key, atomic_source, stage): the earliest atomic source, else the earliest aggregate, flagged."""
    at = F.struct("released_at", "dataset_no", "dataset_id")
    role = role_of(F.col("dataset_no"))
    best = states.groupBy("key").agg(F.min(F.when(role == ATOMIC, at)).alias("atom"), F.min(F.when(role == AGGREGATE, at)).alias("aggr"))
    return best.filter("atom IS NOT NULL OR aggr IS NOT NULL").select("key", F.coalesce("atom.dataset_id", "aggr.dataset_id").alias("atomic_source"), F.when(F.col("atom").isNotNull(), "exact").otherwise("via_aggregate").alias("stage"))


def attribute_exact(items: DataFrame, plan: str = "aggregate_join", level: str = "raw") -> DataFrame:
    """Training items with (atomic_source, stage); stage is exact, via_aggregate or unmatched.

    "aggregate_join" shuffles keys twice and lets adaptive execution split a hot key; "window"
    shuffles once and sorts, which suits small inputs.
    """
    return attribute_keyed(keyed(items, level), plan)


def attribute_keyed(rows: DataFrame, plan: str = "aggregate_join") -> DataFrame:
    """The same for rows that have their keys."""
    if plan == "window":
        w = Window.partitionBy("key")
        at = F.struct("released_at", "dataset_no", "dataset_id")
        role = role_of(F.col("dataset_no"))
        rows = rows.withColumn("atom", F.min(F.when(role == ATOMIC, at)).over(w)).withColumn("aggr", F.min(F.when(role == AGGREGATE, at)).over(w))
        known = F.col("key").isNotNull()
        rows = rows.filter(role == TRAINING).withColumn("atomic_source", F.when(known, F.coalesce("atom.dataset_id", "aggr.dataset_id"))).withColumn("stage", F.when(known & F.col("atom").isNotNull(), "exact").when(known & F.col("aggr").isNotNull(), "via_aggregate").otherwise("unmatched"))
        return rows.drop("atom", "aggr")
    found = origins(set_states(rows))
    return rows.filter(role_of(F.col("dataset_no")) == TRAINING).join(found, "key", "left").withColumn("stage", F.coalesce("stage", F.lit("unmatched")))


def unmatched(items: DataFrame, attributed: DataFrame) -> DataFrame:
    """Items that no stage has attributed."""
    return items.join(attributed.filter("atomic_source IS NOT NULL").select("dataset_id", "item_id"), ["dataset_id", "item_id"], "left_anti")


def strip_instructions(items: DataFrame, rules: list[tuple[str, str]], col: str = "prompt") -> DataFrame:
    """Drop appended instructions; a rule is (pattern, replacement), applied in order."""
    text = F.col(col)
    for pattern, to in rules:
        text = F.regexp_replace(text, pattern, to)
    return items.withColumn(col, F.trim(text))


def inspection_sample(items: DataFrame, n: int = INSPECTED, seed: str = SEED) -> DataFrame:
    """The n items of each set that come first in seeded order; the rank filter limits groups before the shuffle."""
    w = Window.partitionBy("dataset_id").orderBy(seeded(seed, F.col("item_id")))
    return items.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= n)


def release_timeline(dates: DataFrame, date: str, grain: str) -> DataFrame:
    """Releases by period and so far; the window runs over periods, not rows."""
    per = dates.groupBy(F.date_trunc(grain, F.col(date)).cast("date").alias("period")).agg(F.count("*").alias("n"))
    return per.withColumn("so_far", F.sum("n").over(Window.orderBy("period").rowsBetween(Window.unboundedPreceding, 0)))


def hex_key() -> Column:
    return F.lower(F.hex("key"))


__all__ = ["append_to_index", "attribute_exact", "attribute_keyed", "build_index", "content_key", "hex_key", "inspection_sample", "join_key", "keyed", "long_index", "lookup", "merge_metadata", "occurrence_status", "origins", "release_timeline", "set_states", "strip_instructions", "unmatched"]
