"""The composite quality score: static quality, efficiency gain, capability gain, weights that move with model size."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from provspark.config import ScoringConfig
from provspark.functions.keys import scale_law
from provspark.functions.text import is_multi_option


def answer_consistency(keyed_items: DataFrame) -> DataFrame:
    """(dataset_id, r_con): share of a set's distinct prompts whose answers agree wherever they occur.

    Answers are compared in lower case with single spaces; null answers do not count.
    """
    answer = F.lower(F.trim(F.regexp_replace("answer", r"[ \t\r\n]+", " ")))
    rows = keyed_items.filter("key IS NOT NULL").withColumn("a", answer)
    agree = rows.groupBy("key").agg((F.coalesce(F.min("a") == F.max("a"), F.lit(True))).alias("ok"))
    return rows.select("key", "dataset_id").distinct().join(agree, "key").groupBy("dataset_id").agg(F.round(F.avg(F.col("ok").cast("double")), 6).alias("r_con"))


def option_share(items: DataFrame) -> DataFrame:
    return items.groupBy("dataset_id").agg(F.round(F.avg(is_multi_option(F.col("prompt")).cast("double")), 6).alias("r_mcq"))


def reuse_discount(states: DataFrame, form: str = "inverse", free: int = 2) -> DataFrame:
    """(dataset_id, p_reuse) from one row a (key, set); less the more sets share the set's keys."""
    n = states.groupBy("key").agg(F.count("*").alias("n_sets"))
    x = F.col("n_sets")
    value = {
        "inverse": F.least(F.lit(1.0), F.lit(float(free)) / x),
        "log": 1 / (1 + F.ln(F.greatest(F.lit(1.0), x / F.lit(float(free))))),
        "share": F.when(x > free, 0.0).otherwise(1.0),
    }[form]
    return states.select("key", "dataset_id").distinct().join(n, "key").groupBy("dataset_id").agg(F.round(F.avg(value), 6).alias("p_reuse"))


def verifiability(cfg: ScoringConfig) -> Column:
    return F.lit(cfg.con) * F.col("r_con") + F.lit(cfg.mcq) * (1 - F.lit(cfg.mcq_penalty) * F.col("r_mcq")) + F.lit(cfg.reuse) * F.col("p_reuse")


def normalized_entropy(decomposition: DataFrame, max_categories: bool = False) -> DataFrame:
    """(dataset_id, entropy) of shares over ln of the sources present, or of all sources; 0 for one source."""
    h = F.sum(F.when(F.col("share") > 0, -F.col("share") * F.ln("share")).otherwise(0.0))
    per = decomposition.groupBy("dataset_id").agg(h.alias("h"), F.count("*").alias("k"))
    if max_categories:
        k = decomposition.agg(F.count_distinct("origin").alias("k"))
        per = per.drop("k").crossJoin(F.broadcast(k))
    return per.select("dataset_id", F.round(F.when(F.col("k") > 1, F.col("h") / F.ln("k")).otherwise(0.0), 6).alias("entropy"))


def sigmoid(x: Column) -> Column:
    return 1 / (1 + F.exp(-x))


def learnability_score(l_score: Column, entropy: Column, cfg: ScoringConfig) -> Column:
    s = sigmoid(l_score) + F.lit(cfg.diversity) * entropy
    return F.least(s, F.lit(1.0)) if cfg.clip_learnability else s


def contamination_free(items: DataFrame, pairs: DataFrame) -> DataFrame:
    """(dataset_id, s1c): 1 less leaked items over all items."""
    leaked = pairs.select("dataset_id", "item_id").distinct().groupBy("dataset_id").agg(F.count("*").alias("leaked"))
    return items.groupBy("dataset_id").agg(F.count("*").alias("n")).join(leaked, "dataset_id", "left").select("dataset_id", F.round(1 - F.coalesce("leaked", F.lit(0)) / F.col("n"), 6).alias("s1c"))


def static_quality(cfg: ScoringConfig, size: Column) -> Column:
    w = lambda law: scale_law(law, size)
    return w(cfg.verifiability_weight) * F.col("s1a") + w(cfg.learnability_weight) * F.col("s1b") + w(cfg.contamination_weight) * F.col("s1c")


def normalize_gain(df: DataFrame, col: str, how: str = "minmax", base: str | None = None, by: list[str] = ()) -> Column:
    """A gain on a common scale: minmax over sets, headroom, relative to base, or over the largest."""
    w = Window.partitionBy(*by)
    x = F.col(col)
    if how == "minmax":
        lo, hi = F.min(x).over(w), F.max(x).over(w)
        return F.when(hi > lo, (x - lo) / (hi - lo)).otherwise(0.5)
    if how == "headroom":
        return x / (1 - F.col(base))
    if how == "relative":
        return x / F.col(base)
    if how == "max":
        return x / F.max(x).over(w)
    raise ValueError(how)


def blend(gain: Column, l_score: Column, share: Column) -> Column:
    return share * gain + (1 - share) * l_score


def dynamic_parts(parts: DataFrame, cfg: ScoringConfig) -> DataFrame:
    """Parts with s2 and s3: a set's Mean@k and Pass@k gains on the scale of all sets, each blended with learnability.

    parts: (scale, model_size, dataset_id, d_mean, d_pass, l, ...).
    """
    share = scale_law(cfg.gain_share, F.col("model_size"))
    part = lambda gain: F.round(blend(normalize_gain(parts, gain, by=["scale"]), F.col("l"), share), 6)
    return parts.withColumn("s2", part("d_mean")).withColumn("s3", part("d_pass"))


def scales_table(spark, cfg: ScoringConfig) -> DataFrame:
    return spark.createDataFrame(list(zip(cfg.names, cfg.scales)), "scale string, model_size double")


def weights_at(scales: DataFrame, cfg: ScoringConfig) -> DataFrame:
    m = F.col("model_size")
    return scales.select("scale", *[F.round(scale_law(law, m), 6).alias(n) for n, law in (("w1", cfg.w1), ("w2", cfg.w2), ("w3", cfg.w3), ("lambda", cfg.gain_share))])


def quality(cfg: ScoringConfig, size: Column, drop: tuple[str, ...] = ()) -> Column:
    parts = {"s1": cfg.w1, "s2": cfg.w2, "s3": cfg.w3}
    return sum((scale_law(law, size) * F.col(p) for p, law in parts.items() if p not in drop), F.lit(0.0))


def ranked_card(parts: DataFrame, cfg: ScoringConfig, drop: tuple[str, ...] = ()) -> DataFrame:
    """(scale, dataset, s1, s2, s3, q, rank) from parts with ``model_size``; ranks descend, equal scores share the lesser."""
    out = parts.withColumn("q", F.round(quality(cfg, F.col("model_size"), drop), 6))
    return out.withColumn("rank", F.rank().over(Window.partitionBy("scale").orderBy(F.desc("q"))).cast("bigint"))


def fit_weights(card: DataFrame) -> DataFrame:
    """(scale, w1, w2, w3): least squares of q on the parts, by sums and Cramer's rule in column algebra."""
    s = lambda a, b: F.sum(F.col(a) * F.col(b))
    names = ["s1", "s2", "s3"]
    sums = card.groupBy("scale").agg(*[s(a, b).alias(f"{a}{b}") for i, a in enumerate(names) for b in names[i:]], *[s(a, "q").alias(f"{a}q") for a in names])
    c = lambda a, b: F.col(min(a, b) + max(a, b))
    matrix = [[c(a, b) for b in names] for a in names]
    right = [F.col(f"{a}q") for a in names]

    def det(m):
        return m[0][0] * (m[1][1] * m[2][2] - m[1][2] * m[2][1]) - m[0][1] * (m[1][0] * m[2][2] - m[1][2] * m[2][0]) + m[0][2] * (m[1][0] * m[2][1] - m[1][1] * m[2][0])

    whole = det(matrix)
    swap = lambda k: det([[right[i] if j == k else matrix[i][j] for j in range(3)] for i in range(3)])
    return sums.select("scale", *[F.round(swap(k) / whole, 3).alias(f"w{k + 1}") for k in range(3)])


def grid_search(parts: DataFrame, averages: DataFrame, steps: int = 10) -> DataFrame:
    """(scale, w1, w2, w3, pearson): weights on a grid of the simplex that correlate best with averages.

    The grid is (steps + 1)(steps + 2) / 2 rows; the joined table is a row a grid point, set and scale.
    """
    spark = parts.sparkSession
    grid = spark.range(steps + 1).select((F.col("id") / steps).alias("w1"), F.col("id").alias("i")).withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(steps) - F.col("i")))).select("w1", (F.col("j") / steps).alias("w2"), ((F.lit(steps) - F.col("i") - F.col("j")) / steps).alias("w3"))
    rows = parts.join(averages, ["scale", "dataset"]).crossJoin(F.broadcast(grid))
    q = F.col("w1") * F.col("s1") + F.col("w2") * F.col("s2") + F.col("w3") * F.col("s3")
    fit = rows.groupBy("scale", "w1", "w2", "w3").agg(F.round(F.corr(q, F.col("average")), 6).alias("pearson"))
    best = fit.groupBy("scale").agg(F.max(F.struct("pearson", "w1", "w2", "w3")).alias("b"))
    return best.select("scale", F.round("b.w1", 6).alias("w1"), F.round("b.w2", 6).alias("w2"), F.round("b.w3", 6).alias("w3"), "b.pearson")
