"""Curation: leaked items replaced, options dropped or opened, shuffled options."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provspark.functions.keys import seeded
from provspark.functions.text import OPTION_LINE, is_multi_option, option_letters, option_texts
from provspark.operators.shared import cut


def refill_pool(source_items: DataFrame, leaked: DataFrame, learnable: DataFrame, present: DataFrame) -> DataFrame:
    """Items of a source that are no multiple choice, learnable, not leaked and new to the set; one item a key.

    source_items: (item_id, seq, key, options, ...); present: (key) of the set; learnable and leaked: (item_id).
    """
    ok = source_items.filter(~F.col("options")).join(learnable.select("item_id").distinct(), "item_id", "left_semi").join(leaked.select("item_id").distinct(), "item_id", "left_anti").join(present.select("key").distinct(), "key", "left_anti")
    return ok.withColumn("r", F.row_number().over(Window.partitionBy("key").orderBy("seq"))).filter("r = 1").drop("r")


def first_by_seed(pool: DataFrame, n: int, seed: str) -> DataFrame:
    """The n items that come first in seeded order.

    The order is cut into 65,536 bins; bins before the one in which the n-th item falls are taken whole, and only that one is ranked, so
    no task gathers n rows.
    """
    rows = pool.withColumn("seeded", seeded(seed, F.col("item_id"))).withColumn("bin", F.substring("seeded", 1, 4))
    so_far = Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    bins = rows.groupBy("bin").agg(F.count("*").alias("size")).withColumn("before", F.coalesce(F.sum("size").over(so_far), F.lit(0)))
    placed = rows.join(F.broadcast(bins.filter(F.col("before") < n)), "bin")  # 65,536 rows at most
    edge = placed.filter(F.col("before") + F.col("size") > n).withColumn("r", F.row_number().over(Window.partitionBy("bin").orderBy("seeded", "item_id"))).filter(F.col("r") <= n - F.col("before")).drop("r")
    return placed.filter(F.col("before") + F.col("size") <= n).unionByName(edge).drop("seeded", "bin", "size", "before")


def curate(items: DataFrame, leaked: DataFrame, pool: DataFrame, seed: str) -> tuple[DataFrame, dict]:
    """A set without its leaked items, refilled to its size; (items with ``origin``, counts).  ``leaked`` is a written table of item_id."""
    kept = items.join(leaked, "item_id", "left_anti")
    removed = items.count() - kept.count()
    added = cut(first_by_seed(pool, removed, seed), "added")
    n = added.count()
    cols = ["dataset_id", "item_id", "seq", "options"]
    out = kept.select(*cols, F.lit("kept").alias("origin")).unionByName(added.select(*cols, F.lit("added").alias("origin")))
    return out, {"removed": removed, "added": n, "shortfall": removed - n}


def drop_options(items: DataFrame) -> DataFrame:
    return items.filter(~is_multi_option(F.col("prompt")))


def open_ended(items: DataFrame) -> DataFrame:
    """Multiple choice to open questions: options leave the prompt, a letter answer becomes its option's text."""
    options = F.map_from_entries(F.array_distinct(F.zip_with(option_letters(F.col("prompt")), option_texts(F.col("prompt")), lambda a, b: F.struct(a, b))))
    many = F.size(option_letters(F.col("prompt"))) >= 2
    unique = F.size(F.array_distinct(option_letters(F.col("prompt")))) == F.size(option_letters(F.col("prompt")))
    text = F.regexp_replace(F.regexp_replace(F.regexp_replace("prompt", OPTION_LINE, ""), r"\n{2,}", "\n"), r"\s+$", "")
    return items.withColumn("open_answer", F.when(many & unique, F.coalesce(F.try_element_at(options, F.upper("answer")), F.col("answer"))).otherwise(F.col("answer"))).withColumn("open_prompt", F.when(many & unique, text).otherwise(F.col("prompt")))


def shuffle_options(items: DataFrame, seed: str) -> DataFrame:
    """items: (item_id, question, options, answer as a letter).  Options in seeded order, the letter following its option."""
    at = F.ascii("answer") - 64
    order = F.array_sort(F.transform("options", lambda o, i: F.struct(F.sha1(F.concat_ws(":", F.lit(seed), "item_id", i.cast("string"), o).cast("binary")).alias("h"), o.alias("o"), (i + 1).alias("i"))))
    new = items.withColumn("order", order)
    place = F.array_position(F.col("order.i"), at.cast("int"))
    return new.select("item_id", "question", F.col("order.o").alias("options"), F.when(place > 0, F.char(64 + place)).alias("answer"))


def curate_report(before: DataFrame, after: DataFrame, leaked: DataFrame) -> DataFrame:
    """(version, n_items, option_share, leak_rate)."""
    l_ids = leaked.select("item_id").distinct().withColumn("leaked", F.lit(1.0))
    both = before.select(F.lit("before").alias("version"), "item_id", "options").unionByName(after.select(F.lit("after").alias("version"), "item_id", "options"))
    return both.join(l_ids, "item_id", "left").groupBy("version").agg(F.count("*").alias("n_items"), F.round(F.avg(F.col("options").cast("double")), 6).alias("option_share"), F.round(F.avg(F.coalesce("leaked", F.lit(0.0))), 6).alias("leak_rate"))
