"""Audit of candidate matches: a queue of decisions to make, and the decisions applied."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provspark.config import AuditPolicy


def audit(candidates: DataFrame, policy: AuditPolicy, decisions: DataFrame | None = None) -> DataFrame:
    """Candidates (id, other, sim) with status accepted, review or rejected.

    ``decisions`` (id, other, decision) are people's; they override the policy.  Rows in review stay unmatched.
    """
    out = candidates.withColumn("status", F.when(F.col("sim") >= policy.accept, "accepted").when(F.col("sim") >= policy.review, "review").otherwise("rejected"))
    if decisions is not None:
        d = decisions.select("id", "other", "decision")
        out = out.join(d, ["id", "other"], "left").withColumn("status", F.coalesce("decision", "status")).drop("decision")
    return out


def winners(audited: DataFrame, policy: AuditPolicy) -> DataFrame:
    """The best accepted candidates of each item, ties to the least other id."""
    w = Window.partitionBy("id").orderBy(F.desc("sim"), "other")
    return audited.filter("status = 'accepted'").withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= policy.keep_per_item).drop("rank")


def audit_report(audited: DataFrame, truth: DataFrame, low: float, high: float, bands: int) -> DataFrame:
    """(band, n, n_true, precision) of candidates by score band; truth has (id, other)."""
    t = truth.select("id", "other").distinct().withColumn("true", F.lit(1))
    rows = audited.join(t, ["id", "other"], "left").withColumn("band", F.width_bucket("sim", F.lit(low), F.lit(high), F.lit(bands)))
    return rows.groupBy("band").agg(F.count("*").alias("n"), F.count("true").alias("n_true")).withColumn("precision", F.round(F.col("n_true") / F.col("n"), 6))
