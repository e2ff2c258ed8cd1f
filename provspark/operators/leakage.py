"""Leakage of benchmark items into sets: exact, by containment, by similarity; kinds, severity, removal."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provspark.functions.keys import join_key, normalized
from provspark.functions.text import count_cosine, hashed_shingles, is_multi_option, let, placed_runs, words
from provspark.operators.shared import cut

#: Bytes of benchmark text that may be sent to all workers; beyond, joins are left to Spark.
BROADCAST_BYTES = 32 << 20


def sized(table: DataFrame, bench: DataFrame | None = None) -> DataFrame:
    """A table made of the benchmark, to be broadcast if the benchmark's text is within the bound (its size is read, not computed)."""
    text = table if bench is None else bench
    size = text.agg(F.coalesce(F.sum(F.octet_length(F.to_json(F.struct("*")))), F.lit(0))).first()[0]
    return F.broadcast(table) if size <= BROADCAST_BYTES else table


def leak_exact(items: DataFrame, bench: DataFrame, level: str = "raw") -> DataFrame:
    """(dataset_id, item_id, bench_item) with equal keys at a level."""
    b = bench.select(F.col("item_id").alias("bench_item"), join_key(F.col("text"), level).alias("key"))
    return items.select("dataset_id", "item_id", join_key(F.col("prompt"), level).alias("key")).join(sized(b), "key").select("dataset_id", "item_id", "bench_item")


def containment(items: DataFrame, bench: DataFrame, n: int = 5, least: float = 0.0) -> DataFrame:
    """(dataset_id, item_id, bench_item, similarity): share of a benchmark item's n-word shingles that a text holds.

    An equi-join on shingles: only texts that share one meet, and the benchmark side is small.  Items with
    fewer than n words are one shingle, which longer texts do not hold; they match by whole text.
    """
    b = bench.select(F.col("item_id").alias("bench_item"), hashed_shingles(F.col("text"), n).alias("sh")).filter(F.size("sh") > 0)
    each = b.select("bench_item", F.size("sh").alias("size"), F.explode("sh").alias("g"))
    mine = items.select("dataset_id", "item_id", F.explode(hashed_shingles(F.col("prompt"), n)).alias("g"))
    hits = mine.join(sized(each, bench.select("text")), "g").groupBy("dataset_id", "item_id", "bench_item").agg(F.count("*").alias("shared"), F.first("size").alias("size"))
    return hits.withColumn("similarity", F.round(F.col("shared") / F.col("size"), 6)).filter(F.col("similarity") >= least).drop("shared", "size")


def similar_windows(items: DataFrame, bench: DataFrame, least: float = 0.8, anchor: int = 4) -> DataFrame:
    """(dataset_id, item_id, bench_item, at, sim): the passage of each text that is most like a benchmark item.

    A passage has the item's number of words; its similarity is the cosine of word counts.  Passages are those that lay two runs of
    ``anchor`` words of the item (one, if it has no more) over the same runs of the text, an equi-join on hashes; texts that share
    none with the item are not compared.  Equal best passages: the first.
    """
    b = bench.select(F.col("item_id").alias("bench_item"), F.inline(placed_runs(F.col("text"), anchor)).alias("b_at", "g", "m"))
    mine = items.select("dataset_id", "item_id", F.inline(placed_runs(F.col("prompt"), anchor)).alias("p_at", "g", "n"))
    at = F.least(F.greatest(F.col("p_at") - F.col("b_at"), F.lit(0)), F.greatest(F.col("n") - F.col("m"), F.lit(0)))
    cands = cut(mine.join(sized(b, bench.select("text")), "g").select("dataset_id", "item_id", "bench_item", at.alias("at"), "m", "b_at").groupBy("dataset_id", "item_id", "bench_item", "at", "m").agg(F.count_distinct("b_at").alias("laid")).filter(F.col("laid") >= F.least(F.lit(2), F.greatest(F.lit(1), F.col("m") - (anchor - 1)))).drop("laid"), "passages")
    wanted = cands.groupBy("dataset_id", "item_id").agg(F.collect_list(F.struct("bench_item", "at", "m")).alias("c"))
    each = items.select("dataset_id", "item_id", "prompt").join(wanted, ["dataset_id", "item_id"])
    hashes = F.transform(words(F.col("prompt")), lambda w: F.xxhash64(w))
    passages = each.select("dataset_id", "item_id", F.inline(let(hashes, lambda w: F.transform(F.col("c"), lambda c: F.struct(c["bench_item"].alias("bench_item"), c["at"].alias("at"), F.slice(w, c["at"] + 1, c["m"]).alias("p"))))))
    own = bench.select(F.col("item_id").alias("bench_item"), F.transform(words(F.col("text")), lambda w: F.xxhash64(w)).alias("q"))
    rows = passages.join(sized(own, bench.select("text")), "bench_item").withColumn("sim", F.round(count_cosine(F.col("p"), F.col("q")), 6)).filter(F.col("sim") >= least)
    best = rows.groupBy("dataset_id", "item_id", "bench_item").agg(F.min(F.struct((-F.col("sim")).alias("s"), F.col("at").alias("at"))).alias("x"))
    return best.select("dataset_id", "item_id", "bench_item", F.col("x.at").alias("at"), (-F.col("x.s")).alias("sim"))


def kind_of(pairs: DataFrame, items: DataFrame, bench: DataFrame) -> DataFrame:
    """Pairs with the first kind that holds: verbatim, formatting, option_transformed, embedded, rewritten.

    ``similarity`` is the pairs' containment; a ``cosine`` of their best passage may be there as well.
    """
    cosine = F.coalesce("cosine", F.lit(0.0)) if "cosine" in pairs.columns else F.lit(0.0)
    a = items.select("dataset_id", "item_id", F.col("prompt").alias("p"))
    b = bench.select(F.col("item_id").alias("bench_item"), F.col("text").alias("t"))
    rows = pairs.join(a, ["dataset_id", "item_id"]).join(sized(b), "bench_item")
    same = lambda level: normalized(F.col("p"), level) == normalized(F.col("t"), level)
    kind = (
        F.when(F.col("p") == F.col("t"), "verbatim")
        .when(same("letters"), "formatting")
        .when((is_multi_option(F.col("p")) != is_multi_option(F.col("t"))) & F.col("p").contains(F.col("t")), "option_transformed")
        .when((F.col("similarity") >= 1.0) & (F.length("p") > F.length("t")), "embedded")
        .when((F.col("similarity") >= 0.9) | (cosine >= 0.8), "rewritten")
        .otherwise("partial")
    )
    return rows.withColumn("kind", kind).drop("p", "t")


def bulk_inclusion(pairs: DataFrame, bench: DataFrame, min_share: float) -> DataFrame:
    """(dataset_id, benchmark_id, hit_share): benchmarks of which a set holds at least a share."""
    size = bench.groupBy("benchmark_id").agg(F.count("*").alias("size"))
    hit = pairs.join(sized(bench.select(F.col("item_id").alias("bench_item"), "benchmark_id")), "bench_item").groupBy("dataset_id", "benchmark_id").agg(F.count_distinct("bench_item").alias("hit"))
    return hit.join(size, "benchmark_id").withColumn("hit_share", F.round(F.col("hit") / F.col("size"), 6)).filter(F.col("hit_share") >= min_share).select("dataset_id", "benchmark_id", "hit_share")


def severity(pairs: DataFrame, items: DataFrame, bench: DataFrame) -> DataFrame:
    """(dataset_id, benchmark_id, n, rate): distinct leaked items by set and benchmark, with totals of each."""
    size = items.groupBy("dataset_id").agg(F.count("*").alias("size"))
    rows = pairs.join(sized(bench.select(F.col("item_id").alias("bench_item"), "benchmark_id")), "bench_item")
    n = rows.cube("dataset_id", "benchmark_id").agg(F.count_distinct("item_id").alias("n"), F.grouping_id().cast("bigint").alias("level"))
    return n.join(size, "dataset_id", "left").select("dataset_id", "benchmark_id", "level", "n", F.round(F.col("n") / F.col("size"), 6).alias("rate"))


def decontaminate(items: DataFrame, pairs: DataFrame) -> DataFrame:
    return items.join(pairs.select("dataset_id", "item_id").distinct(), ["dataset_id", "item_id"], "left_anti")


def leak_total(pairs: DataFrame) -> DataFrame:
    """(dataset_id, n_leaked) with the total under a null set; an item counts once whatever it hits."""
    return pairs.select("dataset_id", "item_id").distinct().rollup("dataset_id").agg(F.count("*").alias("n_leaked"))


def spread_leaks(pairs: DataFrame, keyed_items: DataFrame) -> DataFrame:
    """One leaked original leaks all its copies: pairs of every item with a leaked key."""
    leaked = pairs.join(keyed_items.select("dataset_id", "item_id", "key"), ["dataset_id", "item_id"]).select("key", "bench_item").distinct()
    return keyed_items.select("dataset_id", "item_id", "key").join(leaked, "key").select("dataset_id", "item_id", "bench_item")


def windows_of(items: DataFrame, width: int, step: int) -> DataFrame:
    """(dataset_id, item_id, at, window): runs of ``width`` words every ``step`` words."""
    def cut(w):
        last = F.greatest(F.size(w) - width, F.lit(0))
        starts = F.array_distinct(F.transform(F.sequence(F.lit(0), last + (step - 1), F.lit(step)), lambda s: F.least(s, last)))
        return F.when(F.size(w) > 0, F.transform(starts, lambda s: F.struct(s.alias("at"), F.array_join(F.slice(w, s + 1, width), " ").alias("window"))))

    return items.select("dataset_id", "item_id", F.inline(let(words(F.col("prompt")), cut)))


def best_window(pairs: DataFrame) -> DataFrame:
    w = Window.partitionBy("dataset_id", "item_id", "bench_item").orderBy(F.desc("similarity"), "at")
    return pairs.withColumn("r", F.row_number().over(w)).filter("r = 1").drop("r")
