"""Attribution by intervention on sources: outcome classes of items and the learnability of sets."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from provspark.config import ScoringConfig
from provspark.functions.keys import outcome_code, scale_law
from provspark.operators.evaluation import mean_at_k, pass_at_k

CODES = ("00", "01", "10", "11")


def pair_outcomes(base: DataFrame, tuned: DataFrame) -> DataFrame:
    """(source, item_id, base_ok, tuned_ok): verdicts of both models on an item of the tuned model's own source."""
    return base.join(tuned, ["source", "item_id"], "full")


def class_shares(pairs: DataFrame, by: list[str]) -> DataFrame:
    """(by..., p00, p01, p10, p11, n, n_missing), missing verdicts being left out of the shares."""
    code = outcome_code(F.col("base_ok"), F.col("tuned_ok"))
    rows = pairs.withColumn("code", code)
    aggs = [F.round(F.avg(F.when(F.col("code").isNotNull(), (F.col("code") == c).cast("double"))), 6).alias(f"p{c}") for c in CODES]
    return rows.groupBy(*by).agg(*aggs, F.count("code").alias("n"), F.count_if(F.col("code").isNull()).alias("n_missing"))


def class_counts(pairs: DataFrame) -> DataFrame:
    return pairs.withColumn("code", outcome_code(F.col("base_ok"), F.col("tuned_ok"))).filter("code IS NOT NULL").groupBy(F.substring("code", 1, 1).alias("base"), F.substring("code", 2, 1).alias("tuned")).agg(F.count("*").alias("n"))


def learnability(cfg: ScoringConfig, size: Column) -> Column:
    """Weighted shares; the weights follow the size law."""
    return sum((scale_law(getattr(cfg, f"alpha{c}"), size) * F.col(f"p{c}") for c in ("01", "11", "10", "00")), F.lit(0.0))


def learnable(pairs: DataFrame) -> DataFrame:
    return pairs.filter(outcome_code(F.col("base_ok"), F.col("tuned_ok")) == "01")


def propagate_labels(labelled: DataFrame, keyed_items: DataFrame) -> DataFrame:
    """A label made once, carried to every item with the key: (dataset_id, item_id, base_ok, tuned_ok).

    Where copies were labelled differently, the label of the least item is taken.
    """
    one = labelled.groupBy("key").agg(F.min_by(F.struct("base_ok", "tuned_ok"), F.col("seq")).alias("l"))
    return keyed_items.select("dataset_id", "item_id", "key").join(one, "key").select("dataset_id", "item_id", "l.base_ok", "l.tuned_ok")


def source_gains(rollouts: DataFrame, base: str, k: int = 4) -> DataFrame:
    """(source, d_mean, d_pass): Mean@k and Pass@k of the checkpoint tuned on each source, less those of the base model.

    rollouts: (model, item, sample, reward) on the validation items, a model being ``base`` or a source.
    """
    both = mean_at_k(rollouts, k).select("model", "mean_at_k").join(pass_at_k(rollouts, k).select("model", "pass_at_k"), "model")
    start = both.filter(F.col("model") == base).select(F.col("mean_at_k").alias("m0"), F.col("pass_at_k").alias("p0"))
    return both.filter(F.col("model") != base).crossJoin(F.broadcast(start)).select(F.col("model").alias("source"), F.round(F.col("mean_at_k") - F.col("m0"), 6).alias("d_mean"), F.round(F.col("pass_at_k") - F.col("p0"), 6).alias("d_pass"))


def mixture_gain(decomposition: DataFrame, gains: DataFrame, *cols: str) -> DataFrame:
    """(dataset_id, cols): a set's gains as the share-weighted gains of its sources; sources without one give nothing."""
    g = gains.select(F.col("source").alias("origin"), *cols)
    return decomposition.join(g, "origin", "left").groupBy("dataset_id").agg(*[F.round(F.sum(F.col("share") * F.coalesce(c, F.lit(0.0))), 6).alias(c) for c in cols])


def between_within(pairs: DataFrame) -> DataFrame:
    """(total, within, between, share_between) of the variance of the outcome over sources."""
    y = F.col("tuned_ok").cast("double") - F.col("base_ok").cast("double")
    per = pairs.select("source", y.alias("y")).filter("y IS NOT NULL").groupBy("source").agg(F.count("*").alias("n"), F.avg("y").alias("m"), F.var_pop("y").alias("v"))
    moments = per.agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("v")).alias("w"), F.sum(F.col("n") * F.col("m")).alias("s"), F.sum(F.col("n") * F.col("m") * F.col("m")).alias("ss"))
    within, between = F.col("w") / F.col("n"), F.col("ss") / F.col("n") - (F.col("s") / F.col("n")) ** 2
    return moments.select(F.round(within + between, 6).alias("total"), F.round(within, 6).alias("within"), F.round(between, 6).alias("between"), F.round(between / (within + between), 6).alias("share_between"))


def features(texts: list[str], dims: int = 64) -> np.ndarray:
    """Hashed word counts, unit length; the last column is a constant."""
    import zlib

    x = np.zeros((len(texts), dims + 1))
    for i, t in enumerate(texts):
        for w in t.lower().split():
            x[i, zlib.crc32(w.encode()) % dims] += 1
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)
    x[:, dims] = 1
    return x


def logistic(x: np.ndarray, y: np.ndarray, rounds: int = 200, rate: float = 1.0, ridge: float = 1e-3) -> np.ndarray:
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-x @ w))
        w -= rate * (x.T @ (p - y) / max(1, len(y)) + ridge * w)
    return w


def proxy_checkpoints(labelled: DataFrame, general: DataFrame, fit_rows: int = 500) -> DataFrame:
    """A runnable stand-in for tuned models: (source, item_id, base_ok, tuned_ok).

    labelled and general: (source, item_id, text, y).  The base model is fitted on a bounded general sample, the tuned one of a
    source also on its items, in groups of about ``fit_rows``, so no task holds a source; both judge the group.
    """
    first = general.orderBy(F.sha1(F.col("item_id").cast("string").cast("binary")), "item_id").limit(fit_rows).toPandas()
    base = logistic(features(first["text"].fillna("").tolist()), first["y"].to_numpy(float)) if len(first) else np.zeros(65)
    shared = labelled.sparkSession.sparkContext.broadcast((base, features(first["text"].fillna("").tolist()), first["y"].to_numpy(float)))

    parts = labelled.groupBy("source").agg(F.ceil(F.count("*") / fit_rows).cast("int").alias("parts"))
    rows = labelled.join(parts, "source").withColumn("part", F.pmod(F.xxhash64("item_id"), F.col("parts"))).drop("parts")

    def group(pdf: pd.DataFrame) -> pd.DataFrame:
        w0, x0, y0 = shared.value
        x, y = features(pdf["text"].fillna("").tolist()), pdf["y"].to_numpy(float)
        w1 = logistic(np.vstack([x0, x]) if len(x0) else x, np.concatenate([y0, y]))
        return pd.DataFrame({"source": pdf["source"], "item_id": pdf["item_id"], "base_ok": ((x @ w0 > 0) == (y > 0.5)).astype("int32"), "tuned_ok": ((x @ w1 > 0) == (y > 0.5)).astype("int32")})

    return rows.groupBy("source", "part").applyInPandas(group, "source string, item_id long, base_ok int, tuned_ok int")
