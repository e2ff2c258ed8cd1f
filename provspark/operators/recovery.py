"""Iterative recovery of missing upstream sets: profile what is unmatched, add candidates, rerun, drop the useless."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from provspark.config import STOP_SHARE
from provspark.functions.text import is_multi_option
from provspark.operators.shared import cut


def measures() -> list[Column]:
    """What a profile is made of, for each text."""
    p = F.col("prompt")
    return [F.length(p).alias("length"), is_multi_option(p).alias("options"), p.rlike("[0-9]").alias("digits"), p.contains("?").alias("questions")]


def format_profile(items: DataFrame, by: list[str]) -> DataFrame:
    """How texts look: length quartiles, share with options, with digits, with question marks; items may have their measures already."""
    items = items.select(*by, *measures()) if "prompt" in items.columns else items
    q = F.percentile("length", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)))
    share = lambda c: F.round(F.avg(F.when(F.col(c), 1.0).otherwise(0.0)), 6).alias(c)
    out = items.groupBy(*by).agg(F.count("*").alias("n"), q.alias("q"), *[share(c) for c in ("options", "digits", "questions")])
    return out.select(*by, "n", *[F.round(F.col("q")[i], 6).alias(f"length_q{i + 1}") for i in range(3)], "options", "digits", "questions")


def rank_candidates(unmatched: DataFrame, candidates: DataFrame, keys_of_unmatched: DataFrame, keys_of_candidates: DataFrame) -> DataFrame:
    """Candidate sets by exact hits among the unmatched keys, then by closeness of format.

    Profiles are a row a set.  Hits come from a semi-join of keys, not of texts.
    """
    target = format_profile(unmatched, [])
    per = format_profile(candidates, ["dataset_id"])
    t = target.select(*[F.col(c).alias(f"t_{c}") for c in ("length_q2", "options", "digits", "questions")])
    far = F.abs(F.ln((F.col("length_q2") + 1) / (F.col("t_length_q2") + 1))) + sum((F.abs(F.col(c) - F.col(f"t_{c}")) for c in ("options", "digits", "questions")), F.lit(0.0))
    hits = keys_of_candidates.join(keys_of_unmatched.select("key").distinct(), "key", "left_semi").groupBy("dataset_id").agg(F.count_distinct("key").alias("hits"))
    return per.crossJoin(F.broadcast(t)).withColumn("far", F.round(far, 6)).join(hits, "dataset_id", "left").select("dataset_id", F.coalesce("hits", F.lit(0)).alias("hits"), "far")


def recover(items: DataFrame, pool: list[str], candidates: list[list[str]], tau: float = STOP_SHARE, max_rounds: int | None = None) -> tuple[DataFrame, list[dict]]:
    """Attribute keys of ``items`` to upstream sets, adding candidate sets in rounds until few are unmatched.

    items: (key, dataset_id, dataset_no).  ``pool`` names the upstream sets known at first; each round
    tries the next list of candidates.  A round reads the new sets' keys only, but re-dates every key
    they touch: a candidate may be older than known origins.  Candidates that recover nothing are
    dropped and what they re-dated is rolled back.  Gives (key, origin) and the log of rounds.
    """
    spark = items.sparkSession
    keys = cut(items.groupBy("key", "dataset_id", "dataset_no").agg(F.count("*").alias("n")), "keys")
    upstream = keys.filter(F.col("dataset_id").isin(pool))
    all_up = set(pool) | {c for r in candidates for c in r}
    targets = cut(keys.filter(~F.col("dataset_id").isin(sorted(all_up))).groupBy("key").agg(F.sum("n").alias("n")), "targets")
    first = lambda df: df.groupBy("key").agg(F.min(F.struct("dataset_no", "dataset_id")).alias("o"))
    known = cut(targets.join(first(upstream), "key", "left"), "known")
    total, log, kept = targets.agg(F.sum("n")).first()[0] or 0, [], list(pool)

    def unmatched(df: DataFrame) -> int:
        return df.filter("o IS NULL").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]

    left = unmatched(known)
    log.append({"round": 0, "pool": len(kept), "unmatched": left, "kept": 0, "dropped": 0})
    for i, batch in enumerate(candidates, 1):
        if total == 0 or left / total < tau or max_rounds is not None and i > max_rounds:
            break
        new = keys.filter(F.col("dataset_id").isin(batch))
        recovered = {r["dataset_id"] for r in new.join(known.filter("o IS NULL").select("key"), "key", "left_semi").select("dataset_id").distinct().collect()}
        useful = [c for c in batch if c in recovered]
        add = first(new.filter(F.col("dataset_id").isin(useful))).withColumnRenamed("o", "p")
        known = cut(known.join(add, "key", "left").select("key", "n", F.least("o", "p").alias("o")), f"round{i}")
        left = unmatched(known)
        kept += useful
        log.append({"round": i, "pool": len(kept), "unmatched": left, "kept": len(useful), "dropped": len(batch) - len(useful)})
    return known.select("key", "n", F.coalesce("o.dataset_id", F.lit("unknown")).alias("origin")), log


def log_table(spark: SparkSession, log: list[dict]) -> DataFrame:
    return spark.createDataFrame([tuple(x.values()) for x in log], "round bigint, pool bigint, unmatched bigint, kept bigint, dropped bigint")
