"""The whole trace: keys first, then similarity under audit for what keys leave, and rounds that look for missing upstream sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provspark.config import STOP_SHARE, AuditPolicy
from provspark.operators import wordcounts as W
from provspark.operators.audit import audit, winners
from provspark.operators.lineage import attribute_keyed, keyed
from provspark.operators.recovery import measures, rank_candidates
from provspark.operators.shared import cut, if_few
from provspark.sources.carriers import ATOMIC, TRAINING, role_of


def one_a_key(keys: DataFrame) -> DataFrame:
    """(key, id): the least item of each key, so copies are encoded once."""
    return keys.filter("key IS NOT NULL").groupBy("key").agg(F.min("seq").alias("id"))


def counts_of(rows: DataFrame, chosen: DataFrame) -> DataFrame:
    """Word counts of the keyed rows that ``chosen`` (key, id) names; texts are shuffled only if it is too large for all workers."""
    return W.counted(rows.join(if_few(chosen.withColumnRenamed("id", "seq")), ["key", "seq"]).select(F.col("seq").alias("id"), "key", "prompt"))


def match_similar(left: DataFrame, right: DataFrame, policy: AuditPolicy = AuditPolicy(), decisions: DataFrame | None = None) -> DataFrame:
    """(key, other_key, sim): the accepted match of each counted text of ``left`` in ``right``.

    Candidates are audited, ``decisions`` (id, other, decision) overriding the bands.  Without decisions none is taken from
    the review band, so only an item's best at the acceptance threshold are looked for.
    """
    found = W.matches(left, right, policy.accept, policy.keep_per_item) if decisions is None else W.matches(left, right, policy.review)
    keys = cut(found, "found")
    best = winners(audit(keys.select("id", "other", "sim"), policy, decisions), policy)
    return best.join(keys.select("id", "other", "key", "other_key"), ["id", "other"]).select("key", "other_key", "sim")


def trace(items: DataFrame, policy: AuditPolicy = AuditPolicy(), level: str = "raw", decisions: DataFrame | None = None) -> DataFrame:
    """Training items with (atomic_source, stage, sim); stage is exact, via_aggregate, semantic or unknown.

    What keys leave unmatched is matched by similarity with the upstream sets' texts; an item then gets the source of its match.
    """
    rows = keyed(items, level)
    keys = cut(rows.select("dataset_id", "dataset_no", "item_id", "released_at", "seq", "key"), "keys")
    by_key = cut(attribute_keyed(keys).select("dataset_id", "item_id", "seq", "key", "atomic_source", "stage"), "attributed")
    up = keys.filter(role_of(F.col("dataset_no")) != TRAINING)
    first = F.min(F.struct(F.when(role_of(F.col("dataset_no")) == ATOMIC, 0).otherwise(1).alias("a"), "released_at", "dataset_no", "dataset_id"))
    source = up.filter("key IS NOT NULL").groupBy(F.col("key").alias("other_key")).agg(first.alias("f")).select("other_key", F.col("f.dataset_id").alias("similar_source"))
    left, right = counts_of(rows, one_a_key(by_key.filter("atomic_source IS NULL"))), counts_of(rows, one_a_key(up))
    found = match_similar(left, right, policy, decisions).join(source, "other_key").select("key", "similar_source", "sim")
    out = by_key.join(found, "key", "left")
    stage = F.when(F.col("atomic_source").isNotNull(), F.col("stage")).when(F.col("similar_source").isNotNull(), "semantic").otherwise("unknown")
    return out.select("dataset_id", "item_id", "seq", F.coalesce("atomic_source", "similar_source").alias("atomic_source"), stage.alias("stage"), F.when(F.col("atomic_source").isNull(), F.col("sim")).alias("sim"))


def recover_sources(targets: DataFrame, sets: DataFrame, pool: list[str], repository: list[str], policy: AuditPolicy = AuditPolicy(), tau: float = STOP_SHARE, per_round: int = 2, least_matches: int = 1) -> tuple[DataFrame, list[dict]]:
    """(key, n, origin, stage) of the targets' keys, and the log of rounds.

    targets and sets: items.  In each round the sets of ``repository`` that look most like what is unmatched (by key hits, then by
    format) join the pool and the keys and similarity stages run again, on what is unmatched and those sets alone.  A set with
    fewer than ``least_matches`` audited matches leaves again, with all that it matched.  Rounds end when the unmatched share is below ``tau``
    or no candidate is left; what is then unmatched is unknown.
    """
    # Texts are read once for what they look like and once for their words; rounds work on keys, measures and counts.
    brief = lambda df: keyed(df).select("dataset_id", "dataset_no", "released_at", "seq", "key", *measures())
    sought, offered = cut(brief(targets), "sought"), cut(brief(sets), "offered")
    mine = cut(one_a_key(sought).join(sought.filter("key IS NOT NULL").groupBy("key").agg(F.count("*").alias("n")), "key"), "targets")
    counts = cut(counts_of(keyed(targets), mine.select("key", "id")), "counts")
    known = cut(mine.select("key", "n", F.lit(None).cast("string").alias("origin"), F.lit(None).cast("string").alias("stage")), "known")
    total = mine.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    remaining, log, kept, number = list(repository), [], [], 0
    batch = list(pool)
    while True:
        new = offered.filter(F.col("dataset_id").isin(batch)).filter("key IS NOT NULL")
        rest = mine.join(known.filter("origin IS NULL").select("key"), "key", "left_semi")
        at = F.struct("released_at", "dataset_no", "dataset_id")
        origin = new.groupBy("key").agg(F.min(at).alias("o")).select("key", F.col("o.dataset_id").alias("set"))
        exact = rest.select("key").join(origin, "key").select("key", "set", F.lit("exact").alias("how"))
        open_ = counts.join(if_few(rest.join(exact.select("key"), "key", "left_anti").select("key")), "key", "left_semi")
        near = match_similar(open_, counts_of(keyed(sets.filter(F.col("dataset_id").isin(batch))), one_a_key(new)), policy).join(origin.withColumnRenamed("key", "other_key"), "other_key").select("key", "set", F.lit("semantic").alias("how"))
        found = cut(exact.unionByName(near), "found")
        matched = {r["set"]: r["c"] for r in found.groupBy("set").agg(F.count("*").alias("c")).collect()}
        useful = [d for d in batch if matched.get(d, 0) >= least_matches or number == 0]
        found = found.filter(F.col("set").isin(useful))
        known = cut(known.join(found, "key", "left").select("key", "n", F.coalesce("origin", "set").alias("origin"), F.coalesce("stage", "how").alias("stage")), "known")
        left = known.filter("origin IS NULL").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        kept += useful
        log.append({"round": number, "tried": ",".join(sorted(batch)), "kept": ",".join(sorted(useful)), "unmatched": left})
        number += 1
        if not remaining or not total or left / total < tau:
            break
        open_keys = sought.join(known.filter("origin IS NULL").select("key"), "key", "left_semi")
        candidates = offered.filter(F.col("dataset_id").isin(remaining))
        ranked = rank_candidates(open_keys, candidates, open_keys, candidates).orderBy(F.desc("hits"), "far", "dataset_id").limit(per_round).collect()
        batch = [r["dataset_id"] for r in ranked]
        if not batch:
            break
        remaining = [d for d in remaining if d not in batch]
    return known.select("key", "n", F.coalesce("origin", F.lit("unknown")).alias("origin"), F.coalesce("stage", F.lit("unknown")).alias("stage")), log


def rounds_table(spark: SparkSession, log: list[dict]) -> DataFrame:
    return spark.createDataFrame([tuple(x.values()) for x in log], "round bigint, tried string, kept string, unmatched bigint")


__all__ = ["match_similar", "recover_sources", "rounds_table", "trace"]
