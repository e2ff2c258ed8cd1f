"""Evaluation measures: Mean@k, Pass@k, core averages, gains, spreads, ranks, correlations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def first_k(rollouts: DataFrame, k: int, cell: list[str]) -> DataFrame:
    """The first k samples of each cell; the rank filter limits groups before the shuffle."""
    w = Window.partitionBy(*cell).orderBy("sample")
    return rollouts.withColumn("rn", F.row_number().over(w)).filter(F.col("rn") <= k)


def per_item(rollouts: DataFrame, k: int, cell: list[str]) -> DataFrame:
    """(cell, mean, any_ok, n, short): of the first k samples; ``short`` cells have fewer."""
    return first_k(rollouts, k, cell).groupBy(*cell).agg(F.avg("reward").alias("mean"), F.max("reward").alias("any_ok"), F.count("*").alias("n")).withColumn("short", F.col("n") < k)


def mean_at_k(rollouts: DataFrame, k: int, cell: list[str] = ("model", "item")) -> DataFrame:
    """(model, mean_at_k, n_items, n_short): the mean over items of the mean reward of their first k samples."""
    cell = list(cell)
    return per_item(rollouts, k, cell).groupBy("model").agg(F.round(F.avg("mean"), 6).alias("mean_at_k"), F.count("*").alias("n_items"), F.count_if("short").alias("n_short"))


def pass_at_k(rollouts: DataFrame, k: int, cell: list[str] = ("model", "item")) -> DataFrame:
    cell = list(cell)
    return per_item(rollouts, k, cell).groupBy("model").agg(F.round(F.avg("any_ok"), 6).alias("pass_at_k"), F.count("*").alias("n_items"), F.count_if("short").alias("n_short"))


def pass_at_k_unbiased(rollouts: DataFrame, k: int) -> DataFrame:
    """1 - C(n - c, k) / C(n, k) from all n samples with c successes, as a running product; null where n < k."""
    cells = rollouts.groupBy("model", "item").agg(F.count("*").alias("n"), F.sum("reward").alias("c"))
    misses = F.aggregate(F.sequence(F.lit(0), F.lit(k - 1)), F.lit(1.0), lambda acc, i: acc * F.greatest(F.lit(0.0), (F.col("n") - F.col("c") - i).cast("double")) / (F.col("n") - i))
    return cells.withColumn("p", F.when(F.col("n") >= k, 1 - misses)).groupBy("model").agg(F.round(F.avg("p"), 6).alias("pass_at_k"), F.count("p").alias("n_items"))


def core_average(results: DataFrame, by: list[str], exclude: str) -> DataFrame:
    """The plain mean over benchmarks other than the validation one."""
    return results.groupBy(*by).agg(F.round(F.avg(F.when(F.col("benchmark") != exclude, F.col("value"))), 6).alias("average"))


def gain_vs_base(results: DataFrame, base: str = "base") -> DataFrame:
    b = results.filter(F.col("dataset") == base).select("scale", "benchmark", F.col("value").alias("base_value"))
    return results.filter(F.col("dataset") != base).join(b, ["scale", "benchmark"]).select("scale", "dataset", "benchmark", F.round(F.col("value") - F.col("base_value"), 6).alias("gain"))


def best_checkpoint(curve: DataFrame) -> DataFrame:
    """(run, step, score): the top validation score of a run, ties to the earliest step."""
    return curve.groupBy("run").agg(F.max(F.struct("score", (-F.col("step")).alias("s"))).alias("b")).select("run", (-F.col("b.s")).alias("step"), "b.score")


def spread(averages: DataFrame) -> DataFrame:
    """(scale, spread, weight): sample deviation of averages at each scale and its share of the sum."""
    s = averages.groupBy("scale").agg(F.stddev_samp("average").alias("s"))
    return s.select("scale", F.round("s", 6).alias("spread"), F.round(F.col("s") / F.sum("s").over(Window.partitionBy()), 6).alias("weight"))


def weighted_rank(averages: DataFrame) -> DataFrame:
    """(dataset, score, rank): ranks at each scale weighed by how far the scale tells sets apart; ties share the lesser rank."""
    r = averages.withColumn("r", F.rank().over(Window.partitionBy("scale").orderBy(F.desc("average"))))
    w = averages.groupBy("scale").agg(F.stddev_samp("average").alias("s"))
    score = r.join(w, "scale").groupBy("dataset").agg(F.round(F.sum(F.col("r") * F.col("s")) / F.sum("s"), 6).alias("score"))
    return score.withColumn("rank", F.rank().over(Window.orderBy("score")).cast("bigint"))


def unweighted_rank(averages: DataFrame) -> DataFrame:
    r = averages.withColumn("r", F.rank().over(Window.partitionBy("scale").orderBy(F.desc("average"))))
    return r.groupBy("dataset").agg(F.round(F.avg("r"), 6).alias("score"))


def average_rank(value: Column, by: list[str]) -> Column:
    """Ranks from the least value, ties sharing their mean."""
    w = Window.partitionBy(*by)
    return F.rank().over(w.orderBy(value)) + (F.count("*").over(Window.partitionBy(*by, value)) - 1) / 2


def correlations(card: DataFrame, averages: DataFrame, parts: list[str] = ("s1", "s2", "s3", "q")) -> DataFrame:
    """(scale, part, pearson, spearman) of score parts with averages.  Runs over a row a set and scale."""
    long = card.join(averages, ["scale", "dataset"]).select("scale", "dataset", "average", F.explode(F.array(*[F.struct(F.lit(p).alias("part"), F.col(p).cast("double").alias("value")) for p in parts])).alias("x")).select("scale", "dataset", "average", "x.part", "x.value")
    by = ["scale", "part"]
    ranked = long.withColumn("ra", average_rank(F.col("average"), by)).withColumn("rv", average_rank(F.col("value"), by))
    return ranked.groupBy(*by).agg(F.round(F.corr("value", "average"), 6).alias("pearson"), F.round(F.corr("rv", "ra"), 6).alias("spearman"))


def group_advantage(rollouts: DataFrame) -> DataFrame:
    """(model, item, sample, advantage): reward less its group's mean, over the group's deviation; 0 in flat groups."""
    w = Window.partitionBy("model", "item")
    s = F.stddev_pop("reward").over(w)
    return rollouts.select("model", "item", "sample", F.round(F.when(s > 0, (F.col("reward") - F.avg("reward").over(w)) / s).otherwise(0.0), 6).alias("advantage"))


def ablation_delta(results: DataFrame, exclude: str) -> DataFrame:
    """(study, subject, benchmark, delta): after less before, with the core average."""
    core = results.filter(F.col("benchmark") != exclude).groupBy("study", "subject", "arm").agg(F.avg("value").alias("value")).withColumn("benchmark", F.lit("core"))
    both = results.unionByName(core)
    return both.groupBy("study", "subject", "benchmark").agg(F.round(F.sum(F.when(F.col("arm") == "after", F.col("value")).otherwise(-F.col("value"))), 6).alias("delta"))
