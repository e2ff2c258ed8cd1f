"""Attribution, evaluation, scoring, ranking and curation queries."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from provspark.config import SEED, ScaleLaw, ScoringConfig
from provspark.operators import attribution as A
from provspark.operators import curation as U
from provspark.operators import evaluation as E
from provspark.operators import lineage as L
from provspark.operators import provenance as P
from provspark.operators import scoring as S
from provspark.operators.shared import cut
from provspark.plans.leak_queries import leak_sql, sure_pairs
from provspark.plans.registry import query, with_items
from provspark.sources import carriers as C
from provspark.sources import published as X

CFG = ScoringConfig()
PAIRS = "(SELECT source, d.doc_id AS item_id, toxic AS base_ok, quality AS tuned_ok, toxic || '' || quality AS code FROM documents d JOIN labels l ON d.doc_id = l.doc_id)"


def share_sql(by: str) -> str:
    cols = ", ".join(f"round(avg(CASE WHEN code IS NOT NULL THEN CASE WHEN code = '{c}' THEN 1.0 ELSE 0.0 END END), 6) AS p{c}" for c in A.CODES)
    return f"SELECT {by}, {cols}, count(code) AS n, count(*) FILTER (code IS NULL) AS n_missing FROM {PAIRS} GROUP BY {by}"


@query("outcome_pairs", f"SELECT source, item_id, base_ok, tuned_ok FROM {PAIRS}")
def outcome_pairs(spark, sf):
    o = C.outcomes(spark, sf)
    return A.pair_outcomes(o.select("source", "item_id", "base_ok"), o.select("source", "item_id", "tuned_ok"))


@query("outcome_class", f"SELECT item_id, code FROM {PAIRS}")
def outcome_class(spark, sf):
    return C.outcomes(spark, sf).select("item_id", A.outcome_code(F.col("base_ok"), F.col("tuned_ok")).alias("code"))


@query("class_shares", share_sql("source"))
def class_shares(spark, sf):
    return A.class_shares(C.outcomes(spark, sf), ["source"])


@query("class_transition", f"SELECT substr(code, 1, 1) AS base, substr(code, 2, 1) AS tuned, count(*) AS n FROM {PAIRS} WHERE code IS NOT NULL GROUP BY 1, 2")
def class_transition(spark, sf):
    return A.class_counts(C.outcomes(spark, sf))


LEARN = "1.0 * p01 + 0.3 * p11 + 0.2 * p10 - 0.5 * p00"


@query("learnability", f"SELECT source, round({LEARN}, 6) AS learnability FROM ({share_sql('source')})")
def learnability(spark, sf):
    return A.class_shares(C.outcomes(spark, sf), ["source"]).select("source", F.round(A.learnability(CFG, F.lit(1e9)), 6).alias("learnability"))


TILTED = ScoringConfig(alpha01=ScaleLaw(0.9, 0.1))


@query("learnability_scales", f"SELECT source, scale, round((0.9 + 0.1 * log10(m / 1e9)) * p01 + 0.3 * p11 + 0.2 * p10 - 0.5 * p00, 6) AS learnability FROM ({share_sql('source')}) CROSS JOIN (VALUES ('small', 1.7e9), ('large', 8e9)) AS t(scale, m)")
def learnability_scales(spark, sf):
    shares = A.class_shares(C.outcomes(spark, sf), ["source"])
    return shares.crossJoin(F.broadcast(S.scales_table(spark, TILTED))).select("source", "scale", F.round(A.learnability(TILTED, F.col("model_size")), 6).alias("learnability"))


@query("learnable_items", f"SELECT source, item_id FROM {PAIRS} WHERE code = '01'")
def learnable_items(spark, sf):
    return A.learnable(C.outcomes(spark, sf)).select("source", "item_id")


@query("inherited_annotation", with_items(", l AS (SELECT key, arg_min(toxic, seq) AS base_ok, arg_min(quality, seq) AS tuned_ok FROM items JOIN labels ON doc_id = seq GROUP BY 1) SELECT dataset_id, item_id, base_ok, tuned_ok FROM items JOIN l USING (key)"))
def inherited_annotation(spark, sf):
    items = L.keyed(C.document_items(spark, sf))
    labels = C.table(spark, sf, "labels").select(F.col("doc_id").alias("seq"), F.col("toxic").alias("base_ok"), F.col("quality").alias("tuned_ok"))
    return A.propagate_labels(items.select("seq", "key").join(labels, "seq"), items)


MEAN4 = "SELECT model, item, avg(reward) AS mean, max(reward) AS any_ok, count(*) AS n FROM (SELECT event_type AS model, user_id AS item, CAST(value > 10 AS INT) AS reward, row_number() OVER (PARTITION BY event_type, user_id ORDER BY event_id) AS rn FROM events) WHERE rn <= 4 GROUP BY 1, 2"


@query("mean_at_k", f"SELECT model, round(avg(mean), 6) AS mean_at_k, count(*) AS n_items, count(*) FILTER (n < 4) AS n_short FROM ({MEAN4}) GROUP BY 1")
def mean_at_k(spark, sf):
    return E.mean_at_k(C.rollouts(spark, sf), 4)


@query("mean_at_32", "SELECT model, round(avg(mean), 6) AS mean_at_k, count(*) AS n_items, count(*) FILTER (n < 32) AS n_short FROM (SELECT model, item, avg(reward) AS mean, count(*) AS n FROM (SELECT event_type AS model, user_id % 5 AS item, CAST(value > 10 AS INT) AS reward, row_number() OVER (PARTITION BY event_type, user_id % 5 ORDER BY event_id) AS rn FROM events) WHERE rn <= 32 GROUP BY 1, 2) GROUP BY 1")
def mean_at_32(spark, sf):
    return E.mean_at_k(C.rollouts(spark, sf).withColumn("item", F.col("item") % 5), 32)


@query("pass_at_k", f"SELECT model, round(avg(any_ok), 6) AS pass_at_k, count(*) AS n_items, count(*) FILTER (n < 4) AS n_short FROM ({MEAN4}) GROUP BY 1")
def pass_at_k(spark, sf):
    return E.pass_at_k(C.rollouts(spark, sf), 4)


@query("pass_at_k_unbiased", "SELECT model, round(avg(p), 6) AS pass_at_k, count(p) AS n_items FROM (SELECT model, CASE WHEN n >= 4 THEN 1 - greatest(0, n - c) / n * greatest(0, n - c - 1) / (n - 1) * greatest(0, n - c - 2) / (n - 2) * greatest(0, n - c - 3) / (n - 3) END AS p FROM (SELECT event_type AS model, user_id, count(*) AS n, CAST(sum(CAST(value > 10 AS INT)) AS BIGINT) AS c FROM events GROUP BY 1, 2)) GROUP BY 1")
def pass_at_k_unbiased(spark, sf):
    return E.pass_at_k_unbiased(C.rollouts(spark, sf), 4)


SOURCE_MEAN4 = "SELECT model, item, avg(reward) AS mean, max(reward) AS any_ok FROM (SELECT *, row_number() OVER (PARTITION BY model, item ORDER BY event_id) AS rn FROM (SELECT CASE WHEN event_type = 'view' THEN 'base' ELSE 'src' || (event_id % 5) END AS model, user_id % 50 AS item, event_id, CAST(value > 250 AS INT) AS reward FROM events)) WHERE rn <= 4 GROUP BY 1, 2"
GAIN = f"(SELECT s.model AS source, round(s.m - b.m, 6) AS d_mean, round(s.p - b.p, 6) AS d_pass FROM (SELECT model, round(avg(mean), 6) AS m, round(avg(any_ok), 6) AS p FROM ({SOURCE_MEAN4}) GROUP BY 1) s JOIN (SELECT model, round(avg(mean), 6) AS m, round(avg(any_ok), 6) AS p FROM ({SOURCE_MEAN4}) GROUP BY 1) b ON b.model = 'base' AND s.model <> 'base')"


@query("source_gain", f"SELECT * FROM {GAIN}")
def source_gain(spark, sf):
    """Mean@4 and Pass@4 gains of each atomic source's checkpoint over the base model."""
    return A.source_gains(C.source_rollouts(spark, sf), "base")


@query("base_untrained", f"SELECT round(avg(mean), 6) AS mean_at_4, round(avg(any_ok), 6) AS pass_at_4 FROM ({MEAN4}) WHERE model = 'view'")
def base_untrained(spark, sf):
    """Baseline: the model before any training."""
    r = C.rollouts(spark, sf).filter(F.col("model") == C.BASE_MODEL)
    return E.mean_at_k(r, 4).join(E.pass_at_k(r, 4), "model").select(F.col("mean_at_k").alias("mean_at_4"), F.col("pass_at_k").alias("pass_at_4"))


DECOMP = "SELECT dataset_id, coalesce(atomic_source, 'unknown') AS origin, round(count(*) / sum(count(*)) OVER (PARTITION BY dataset_id), 6) AS share FROM attributed GROUP BY 1, 2"


SET_GAIN = f"SELECT dataset_id, round(sum(share * coalesce(d_mean, 0)), 6) AS d_mean, round(sum(share * coalesce(d_pass, 0)), 6) AS d_pass FROM ({DECOMP}) LEFT JOIN (SELECT source AS origin, d_mean, d_pass FROM {GAIN}) USING (origin) GROUP BY 1"


@query("set_gain_mixture", with_items(SET_GAIN))
def set_gain_mixture(spark, sf):
    """A set's Mean@4 and Pass@4 gains, mixed from those of its sources by their shares."""
    return A.mixture_gain(P.decompose(L.attribute_exact(C.document_items(spark, sf))), source_gain(spark, sf), "d_mean", "d_pass")


@query("intervention_vs_item", f"SELECT round(w + b, 6) AS total, round(w, 6) AS within, round(b, 6) AS between, round(b / (w + b), 6) AS share_between FROM (SELECT sum(n * v) / sum(n) AS w, sum(n * m * m) / sum(n) - (sum(n * m) / sum(n)) * (sum(n * m) / sum(n)) AS b FROM (SELECT source, count(*) AS n, avg(tuned_ok - base_ok) AS m, var_pop(tuned_ok - base_ok) AS v FROM {PAIRS} GROUP BY 1))")
def intervention_vs_item(spark, sf):
    return A.between_within(C.outcomes(spark, sf))


@query("proxy_pairs")
def proxy_pairs(spark, sf):
    docs = C.table(spark, sf, "documents").select("source", F.col("doc_id").alias("item_id"), "text")
    rows = docs.join(C.table(spark, sf, "labels").select(F.col("doc_id").alias("item_id"), F.col("quality").alias("y")), "item_id")
    general = rows.filter("item_id % 2 = 0")
    return A.proxy_checkpoints(rows, general)


# The same measures on events: their cells stand in for accuracies, score parts and ablations.
SCALE, SET = "CASE WHEN user_id % 2 = 0 THEN 'small' ELSE 'large' END", "CASE WHEN event_id % 7 = 0 THEN 'base' ELSE substr('ABCDEF', CAST(event_id % 7 AS INT), 1) END"
CELL = "'b' || ((event_id // 7) % 8) AS benchmark, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) / (count(value) * 100) AS value FROM events GROUP BY ALL)"
LIVE_ACC = f"(SELECT {SCALE} AS scale, {SET} AS dataset, {CELL}"
LIVE_AVG = f"(SELECT scale, dataset, avg(value) AS average FROM {LIVE_ACC} WHERE dataset <> 'base' AND benchmark <> 'b0' GROUP BY 1, 2)"
LIVE_CARD = f"(SELECT *, (s1 + s2 + s3) / 3 AS q FROM (SELECT {SCALE} AS scale, {SET} AS dataset, count(*) FILTER (value <= 50) / count(*) AS s1, count(*) FILTER (event_type IN ('purchase', 'click')) / count(*) AS s2, count(*) FILTER (user_id % 3 = 0) / count(*) AS s3 FROM events GROUP BY 1, 2) WHERE dataset <> 'base')"
LIVE_ABL = f"(SELECT CASE WHEN user_id % 2 = 0 THEN 'options' ELSE 'cleaning' END AS study, 'subject' || (user_id % 3) AS subject, CASE WHEN event_id % 2 = 0 THEN 'before' ELSE 'after' END AS arm, {CELL}"

# Published fixtures.
AVG = X.values_sql(X.AVERAGES, ["scale", "dataset", "average"], 2)
CARD = X.values_sql(X.SCORES, ["scale", "dataset", "s1", "s2", "s3", "q"], 2)


@query("core_average", f"SELECT scale, dataset, round(avg(value) FILTER (benchmark <> 'b0'), 6) AS average FROM {LIVE_ACC} GROUP BY 1, 2")
def core_average(spark, sf):
    return E.core_average(C.results(spark, sf), ["scale", "dataset"], C.VALIDATION)


@query("gain_vs_base", f"SELECT a.scale, a.dataset, a.benchmark, round(a.value - b.value, 6) AS gain FROM {LIVE_ACC} a JOIN {LIVE_ACC} b ON a.scale = b.scale AND a.benchmark = b.benchmark AND b.dataset = 'base' WHERE a.dataset <> 'base'")
def gain_vs_base(spark, sf):
    return E.gain_vs_base(C.results(spark, sf))


@query("base_sets_a_to_e", f"SELECT a.scale, a.dataset, round(f.average - a.average, 6) AS behind FROM {LIVE_AVG} a JOIN {LIVE_AVG} f ON a.scale = f.scale AND f.dataset = 'F' WHERE a.dataset <> 'F'")
def base_sets_a_to_e(spark, sf):
    """Baseline: the five public sets, and how far each is behind the curated one."""
    a = C.set_averages(spark, sf)
    f = a.filter("dataset = 'F'").select("scale", F.col("average").alias("f"))
    return a.filter("dataset <> 'F'").join(f, "scale").select("scale", "dataset", F.round(F.col("f") - F.col("average"), 6).alias("behind"))


@query("best_checkpoint", "SELECT run, max_by(step, (score, -step)) AS step, max(score) AS score FROM (SELECT event_type AS run, event_id % 50 * 10 AS step, round(avg(value), 2) AS score FROM events GROUP BY 1, 2) GROUP BY 1")
def best_checkpoint(spark, sf):
    curve = C.table(spark, sf, "events").groupBy(F.col("event_type").alias("run"), (F.col("event_id") % 50 * 10).alias("step")).agg(F.round(F.avg("value"), 2).alias("score"))
    return E.best_checkpoint(curve)


@query("cross_set_spread", f"SELECT scale, round(s, 6) AS spread, round(s / sum(s) OVER (), 6) AS weight FROM (SELECT scale, stddev_samp(average) AS s FROM {LIVE_AVG} GROUP BY 1)")
def cross_set_spread(spark, sf):
    return E.spread(C.set_averages(spark, sf))


@query("spread_weights", f"SELECT scale, round(s / sum(s) OVER (), 6) AS weight FROM (SELECT scale, stddev_samp(average) AS s FROM {AVG} GROUP BY 1)")
def spread_weights(spark, sf):
    return E.spread(X.averages(spark)).select("scale", "weight")


RANKED = f"(SELECT *, rank() OVER (PARTITION BY scale ORDER BY average DESC) AS r FROM {AVG})"


@query("spread_weighted_rank", f"SELECT dataset, score, rank() OVER (ORDER BY score) AS rank FROM (SELECT dataset, round(sum(r * s) / sum(s), 6) AS score FROM {RANKED} JOIN (SELECT scale, stddev_samp(average) AS s FROM {AVG} GROUP BY 1) USING (scale) GROUP BY 1)")
def spread_weighted_rank(spark, sf):
    return E.weighted_rank(X.averages(spark))


@query("base_unweighted_rank", f"SELECT dataset, round(avg(r), 6) AS score FROM {RANKED.replace(AVG, LIVE_AVG)} GROUP BY 1")
def base_unweighted_rank(spark, sf):
    """Baseline: the plain mean rank."""
    return E.unweighted_rank(C.set_averages(spark, sf))


LONGCARD = f"(SELECT scale, dataset, average, part, value FROM (SELECT * FROM {CARD} JOIN {AVG} USING (scale, dataset)) UNPIVOT (value FOR part IN (s1, s2, s3, q)))"
CORR = f"SELECT scale, part, round(corr(value, average), 6) AS pearson, round(corr(rv, ra), 6) AS spearman FROM (SELECT *, rank() OVER (PARTITION BY scale, part ORDER BY value) + (count(*) OVER (PARTITION BY scale, part, value) - 1) / 2 AS rv, rank() OVER (PARTITION BY scale, part ORDER BY average) + (count(*) OVER (PARTITION BY scale, part, average) - 1) / 2 AS ra FROM {LONGCARD}) GROUP BY 1, 2"


LIVE_CORR = CORR.replace(CARD, LIVE_CARD).replace(AVG, LIVE_AVG)


@query("correlations", LIVE_CORR)
def correlations(spark, sf):
    return E.correlations(C.set_scores(spark, sf), C.set_averages(spark, sf))


@query("pearson", f"SELECT scale, part, pearson FROM ({LIVE_CORR})")
def pearson(spark, sf):
    return correlations(spark, sf).select("scale", "part", "pearson")


@query("spearman", f"SELECT scale, part, spearman FROM ({CORR})")
def spearman(spark, sf):
    return E.correlations(X.scores(spark), X.averages(spark)).select("scale", "part", "spearman")


@query("base_single_part", f"SELECT scale, dataset, rank() OVER (PARTITION BY scale ORDER BY s1 DESC) AS r1, rank() OVER (PARTITION BY scale ORDER BY s2 DESC) AS r2, rank() OVER (PARTITION BY scale ORDER BY s3 DESC) AS r3 FROM {LIVE_CARD}")
def base_single_part(spark, sf):
    """Baseline: sets ranked by one part alone."""
    from pyspark.sql import Window

    rank = lambda c: F.rank().over(Window.partitionBy("scale").orderBy(F.desc(c))).cast("bigint")
    return C.set_scores(spark, sf).select("scale", "dataset", rank("s1").alias("r1"), rank("s2").alias("r2"), rank("s3").alias("r3"))


@query("rank_agreement", f"WITH w AS (SELECT dataset, -round(sum(r * s) / sum(s), 6) AS ref FROM {RANKED} JOIN (SELECT scale, stddev_samp(average) AS s FROM {AVG} GROUP BY 1) USING (scale) GROUP BY 1), j AS (SELECT scale, dataset, q, average, ref FROM {CARD} JOIN {AVG} USING (scale, dataset) JOIN w USING (dataset)), r AS (SELECT scale, rank() OVER (PARTITION BY scale ORDER BY q) AS rq, rank() OVER (PARTITION BY scale ORDER BY average) + (count(*) OVER (PARTITION BY scale, average) - 1) / 2 AS ra, rank() OVER (PARTITION BY scale ORDER BY ref) AS rr FROM j) SELECT scale, round(corr(rq, rr), 6) AS score_reference, round(corr(ra, rr), 6) AS average_reference FROM r GROUP BY 1")
def rank_agreement(spark, sf):
    """Rank correlation of the score, and of one scale's averages, with the reference ranking."""
    ref = E.weighted_rank(X.averages(spark)).select("dataset", (-F.col("score")).alias("ref"))
    rows = X.scores(spark).join(X.averages(spark), ["scale", "dataset"]).join(ref, "dataset")
    for name, col in (("rq", "q"), ("ra", "average"), ("rr", "ref")):
        rows = rows.withColumn(name, E.average_rank(F.col(col), ["scale"]))
    return rows.groupBy("scale").agg(F.round(F.corr("rq", "rr"), 6).alias("score_reference"), F.round(F.corr("ra", "rr"), 6).alias("average_reference"))


@query("group_advantage", "SELECT event_type AS model, user_id AS item, event_id AS sample, round(CASE WHEN s > 0 THEN (r - m) / s ELSE 0 END, 6) AS advantage FROM (SELECT *, CAST(value > 10 AS INT) AS r, avg(CAST(value > 10 AS INT)) OVER w AS m, stddev_pop(CAST(value > 10 AS INT)) OVER w AS s FROM events WINDOW w AS (PARTITION BY event_type, user_id))")
def group_advantage(spark, sf):
    return E.group_advantage(C.rollouts(spark, sf))


@query("ablation_delta", f"WITH a AS (SELECT * FROM {LIVE_ABL} UNION ALL SELECT study, subject, arm, 'core', avg(value) FROM {LIVE_ABL} WHERE benchmark <> 'b0' GROUP BY 1, 2, 3) SELECT study, subject, benchmark, round(sum(CASE WHEN arm = 'after' THEN value ELSE -value END), 6) AS delta FROM a GROUP BY 1, 2, 3")
def ablation_delta(spark, sf):
    return E.ablation_delta(C.arms(spark, sf), C.VALIDATION)


@query("weights_from_scores")
def weights_from_scores(spark, sf):
    return S.fit_weights(X.scores(spark))


@query("scale_law", "SELECT scale, round(0.684 - 0.363 * log10(m / 1e9), 6) AS w1 FROM (VALUES ('small', 1.7e9), ('large', 8e9)) AS t(scale, m)")
def scale_law(spark, sf):
    return S.weights_at(S.scales_table(spark, CFG), CFG).select("scale", "w1")


@query("scale_weights", "SELECT scale, round(0.684 - 0.363 * x, 6) AS w1, round(0.22 + 0.131 * x, 6) AS w2, round(0.096 + 0.232 * x, 6) AS w3, round(0.4 + 0.3 * x, 6) AS lambda FROM (SELECT scale, log10(m / 1e9) AS x FROM (VALUES ('small', 1.7e9), ('large', 8e9)) AS t(scale, m))".replace("AS lambda", 'AS "lambda"'))
def scale_weights(spark, sf):
    return S.weights_at(S.scales_table(spark, CFG), CFG)


def published_card(spark, cfg=CFG, drop=()):
    parts = X.scores(spark).drop("q").join(F.broadcast(S.scales_table(spark, cfg)), "scale")
    return S.ranked_card(parts, cfg, drop).select("scale", "dataset", "q", "rank")


QSQL = "SELECT scale, dataset, q, rank() OVER (PARTITION BY scale ORDER BY q DESC) AS rank FROM (SELECT scale, dataset, round({0}, 6) AS q FROM (SELECT *, log10(CASE WHEN scale = 'small' THEN 1.7 ELSE 8.0 END) AS x FROM " + CARD + "))"


def live_card(spark, sf, cfg=CFG):
    parts = C.set_scores(spark, sf).drop("q").join(F.broadcast(S.scales_table(spark, cfg)), "scale")
    return S.ranked_card(parts, cfg).select("scale", "dataset", "q", "rank")


@query("quality_score", QSQL.format("(0.684 - 0.363 * x) * s1 + (0.22 + 0.131 * x) * s2 + (0.096 + 0.232 * x) * s3").replace(CARD, LIVE_CARD))
def quality_score(spark, sf):
    return live_card(spark, sf)


@query("score_ablation", QSQL.format("(0.684 - 0.363 * x) * s1 + (0.096 + 0.232 * x) * s3"))
def score_ablation(spark, sf):
    """The score without its efficiency part."""
    return published_card(spark, drop=("s2",))


FIXED = ScoringConfig(w1=ScaleLaw(0.5), w2=ScaleLaw(0.3), w3=ScaleLaw(0.2))


@query("base_fixed_weights", QSQL.format("0.5 * s1 + 0.3 * s2 + 0.2 * s3").replace(CARD, LIVE_CARD))
def base_fixed_weights(spark, sf):
    """Baseline: weights that do not move with size."""
    return live_card(spark, sf, FIXED)


@query("score_grid_search", f"WITH g AS (SELECT i / 10 AS w1, j / 10 AS w2, (10 - i - j) / 10 AS w3 FROM range(11) a(i), range(11) b(j) WHERE i + j <= 10), f AS (SELECT scale, w1, w2, w3, round(corr(w1 * s1 + w2 * s2 + w3 * s3, average), 6) AS pearson FROM g CROSS JOIN (SELECT * FROM {CARD} JOIN {AVG} USING (scale, dataset)) GROUP BY 1, 2, 3, 4) SELECT scale, round(w1, 6) AS w1, round(w2, 6) AS w2, round(w3, 6) AS w3, pearson FROM (SELECT *, row_number() OVER (PARTITION BY scale ORDER BY pearson DESC, w1 DESC, w2 DESC) AS r FROM f) WHERE r = 1")
def score_grid_search(spark, sf):
    return S.grid_search(X.scores(spark).drop("q"), X.averages(spark))


# Live parts on documents.
RCON = "SELECT dataset_id, round(avg(CASE WHEN ok THEN 1.0 ELSE 0.0 END), 6) AS r_con FROM (SELECT DISTINCT key, dataset_id FROM items) JOIN (SELECT key, coalesce(min(lower(trim(answer))) = max(lower(trim(answer))), true) AS ok FROM items GROUP BY 1) USING (key) GROUP BY 1"


FIRST_LINE = "SELECT source AS dataset_id, split_part(text, chr(10), 1) AS key, lower(trim(regexp_replace(substr(text, length(split_part(text, chr(10), 1)) + 2), '[ \\t\\r\\n]+', ' ', 'g'))) AS answer FROM documents"
CONSISTENT = RCON.replace("FROM items", f"FROM ({FIRST_LINE})")


def first_line_items(spark, sf):
    """A document's first line as a prompt, what follows as its answer."""
    first = F.split_part("text", F.lit("\n"), F.lit(1))
    d = C.texts(spark, sf, "documents", "source", "text")
    return L.keyed(d.select(F.col("source").alias("dataset_id"), first.alias("prompt"), F.substr("text", F.length(first) + 2).alias("answer")))


@query("answer_consistency", CONSISTENT)
def answer_consistency(spark, sf):
    return S.answer_consistency(first_line_items(spark, sf))


@query("answer_consistency_parts", "SELECT count(*) AS n_prompts, count(*) FILTER (k = 1) AS n_consistent FROM (SELECT p_name || ' ' || p_size AS key, count(DISTINCT p_brand) AS k FROM part GROUP BY 1)")
def answer_consistency_parts(spark, sf):
    p = C.table(spark, sf, "part").select(F.concat_ws(" ", "p_name", F.col("p_size").cast("string")).alias("key"), "p_brand")
    return p.groupBy("key").agg(F.count_distinct("p_brand").alias("k")).agg(F.count("*").alias("n_prompts"), F.count_if(F.col("k") == 1).alias("n_consistent"))


OPTION = "(len(regexp_extract_all({0}, '(?m)^[ \\t]*\\(?([A-H])[).:][ \\t]+(.+?)[ \\t]*$')) >= 2 OR length({0}) - length(replace({0}, '|', '')) >= 2)"


@query("option_share", with_items(f"SELECT dataset_id, round(avg(CASE WHEN {OPTION.format('prompt')} THEN 1.0 ELSE 0.0 END), 6) AS r_mcq FROM items GROUP BY 1"))
def option_share(spark, sf):
    return S.option_share(C.document_items(spark, sf))


REUSE = ", n AS (SELECT key, count(*) AS n_sets FROM ks GROUP BY 1) SELECT dataset_id, round(avg({0}), 6) AS p_reuse FROM ks JOIN n USING (key) GROUP BY 1"
FORMS = {"inverse": "least(1.0, 2 / n_sets)", "log": "1 / (1 + ln(greatest(1.0, n_sets / 2)))", "share": "CASE WHEN n_sets > 2 THEN 0.0 ELSE 1.0 END"}
for _form, _sql in FORMS.items():
    query(f"reuse_discount_{_form}", with_items(REUSE.format(_sql)))(lambda spark, sf, form=_form: S.reuse_discount(L.set_states(L.keyed(C.document_items(spark, sf))), form))
query("reuse_discount", with_items(REUSE.format(FORMS["inverse"])))(lambda spark, sf: S.reuse_discount(L.set_states(L.keyed(C.document_items(spark, sf)))))

ENTROPY = f"SELECT dataset_id, round(CASE WHEN count(*) > 1 THEN -sum(share * ln(share)) / ln(count(*)) ELSE 0 END, 6) AS entropy FROM ({DECOMP}) GROUP BY 1"


@query("source_entropy", with_items(ENTROPY))
def source_entropy(spark, sf):
    return S.normalized_entropy(P.decompose(L.attribute_exact(C.document_items(spark, sf))))


@query("udaf_entropy", with_items(ENTROPY))
def udaf_entropy(spark, sf):
    """The same by a grouped pandas function, for comparison with the built-in form."""
    @F.pandas_udf("double")
    def entropy(share: pd.Series) -> float:
        p = share.to_numpy()
        return round(float(-(p * np.log(p)).sum() / np.log(len(p))), 6) if len(p) > 1 else 0.0

    return P.decompose(L.attribute_exact(C.document_items(spark, sf))).groupBy("dataset_id").agg(entropy("share").alias("entropy"))


S1C = "SELECT dataset_id, round(1 - coalesce(leaked, 0) / n, 6) AS s1c FROM (SELECT dataset_id, count(*) AS n FROM items GROUP BY 1) LEFT JOIN (SELECT dataset_id, count(DISTINCT item_id) AS leaked FROM pairs GROUP BY 1) USING (dataset_id)"


@query("contamination_free", with_items(leak_sql() + S1C))
def contamination_free(spark, sf):
    return S.contamination_free(C.document_items(spark, sf), sure_pairs(spark, sf))


#: The live card moves the weight of learnable items with size, as all coefficients may.
LIVE_CFG = TILTED


def narrow_items(spark, sf):
    """One row a document without its texts, written once: keys, an answer's key, whether it is multiple choice."""
    text, first = F.col("text"), F.split_part("text", F.lit("\n"), F.lit(1))
    answer = F.lower(F.trim(F.regexp_replace(F.substr("text", F.length(first) + 2), r"[ \t\r\n]+", " ")))
    no = C.number_of(F.col("source"))
    rows = C.texts(spark, sf, "documents", "doc_id", "text", "source")
    return cut(rows.select(F.col("source").alias("dataset_id"), no.alias("dataset_no"), C.release_of(no).alias("released_at"), F.col("doc_id").cast("string").alias("item_id"), F.col("doc_id").alias("seq"), L.join_key(text).alias("key"), L.join_key(first).alias("first_key"), L.content_key(answer).alias("answer"), S.is_multi_option(text).alias("options")), "narrow")


def live_parts(spark, sf):
    """One row a set and scale: every part of the score on the documents.

    The texts are read twice, for the keys and for the leaks; all else works on what these wrote.
    """
    rows, pairs = narrow_items(spark, sf), cut(sure_pairs(spark, sf), "pairs")
    decomposition = P.decompose(L.attribute_keyed(rows))
    scales = S.scales_table(spark, LIVE_CFG)
    share = rows.groupBy("dataset_id").agg(F.round(F.avg(F.col("options").cast("double")), 6).alias("r_mcq"))
    learn = A.class_shares(C.outcomes(spark, sf), ["source"]).withColumnRenamed("source", "dataset_id").crossJoin(F.broadcast(scales)).select("dataset_id", "scale", "model_size", F.round(A.learnability(LIVE_CFG, F.col("model_size")), 6).alias("l"))
    parts = S.answer_consistency(rows.select("dataset_id", F.col("first_key").alias("key"), "answer"))
    for other in (share, S.reuse_discount(L.set_states(rows)), S.normalized_entropy(decomposition), S.contamination_free(rows, pairs), A.mixture_gain(decomposition, source_gain(spark, sf), "d_mean", "d_pass"), learn):
        parts = parts.join(other, "dataset_id")
    return parts.withColumn("s1a", F.round(S.verifiability(LIVE_CFG), 6)).withColumn("s1b", F.round(S.learnability_score(F.col("l"), F.col("entropy"), LIVE_CFG), 6))


LIVE = leak_sql() + f""", live AS (SELECT *, round(0.4 * r_con + 0.3 * (1 - 0.5 * r_mcq) + 0.3 * p_reuse, 6) AS s1a, round(1 / (1 + exp(-l)) + 0.1 * entropy, 6) AS s1b
FROM ({CONSISTENT}) JOIN (SELECT dataset_id, round(avg(CASE WHEN {OPTION.format('prompt')} THEN 1.0 ELSE 0.0 END), 6) AS r_mcq FROM items GROUP BY 1) USING (dataset_id)
JOIN (SELECT dataset_id, round(avg(least(1.0, 2 / n_sets)), 6) AS p_reuse FROM ks JOIN (SELECT key, count(*) AS n_sets FROM ks GROUP BY 1) USING (key) GROUP BY 1) USING (dataset_id)
JOIN (SELECT source AS dataset_id, scale, log10(m / 1e9) AS x, round((0.9 + 0.1 * log10(m / 1e9)) * p01 + 0.3 * p11 + 0.2 * p10 - 0.5 * p00, 6) AS l FROM ({share_sql('source')}) CROSS JOIN (VALUES ('small', 1.7e9), ('large', 8e9)) AS t(scale, m)) USING (dataset_id)
JOIN ({ENTROPY}) USING (dataset_id) JOIN ({S1C}) USING (dataset_id) JOIN ({SET_GAIN}) USING (dataset_id)
), parts AS (SELECT *, round(0.35 * s1a + 0.3 * s1b + 0.35 * s1c, 6) AS s1, round((0.4 + 0.3 * x) * gm + (0.6 - 0.3 * x) * l, 6) AS s2, round((0.4 + 0.3 * x) * gp + (0.6 - 0.3 * x) * l, 6) AS s3
FROM (SELECT *, CASE WHEN max(d_mean) OVER w > min(d_mean) OVER w THEN (d_mean - min(d_mean) OVER w) / (max(d_mean) OVER w - min(d_mean) OVER w) ELSE 0.5 END AS gm, CASE WHEN max(d_pass) OVER w > min(d_pass) OVER w THEN (d_pass - min(d_pass) OVER w) / (max(d_pass) OVER w - min(d_pass) OVER w) ELSE 0.5 END AS gp FROM live WINDOW w AS (PARTITION BY scale)))
"""


@query("verifiability", with_items(LIVE + "SELECT DISTINCT dataset_id, s1a FROM live"))
def verifiability(spark, sf):
    return live_parts(spark, sf).select("dataset_id", "s1a").distinct()


@query("learnability_score", with_items(LIVE + "SELECT scale, dataset_id, s1b FROM live"))
def learnability_score(spark, sf):
    return live_parts(spark, sf).select("scale", "dataset_id", "s1b")


def live_scores(spark, sf):
    """S1, S2 from the Mean@4 gains and S3 from the Pass@4 gains, each set's gain on the scale of all sets."""
    parts = live_parts(spark, sf)
    return S.dynamic_parts(parts, LIVE_CFG).withColumn("s1", F.round(S.static_quality(LIVE_CFG, F.col("model_size")), 6))


@query("static_quality", with_items(LIVE + "SELECT scale, dataset_id, s1 FROM parts"))
def static_quality(spark, sf):
    return live_scores(spark, sf).select("scale", "dataset_id", "s1")


MINMAX = "CASE WHEN max({0}) OVER () > min({0}) OVER () THEN ({0} - min({0}) OVER ()) / (max({0}) OVER () - min({0}) OVER ()) ELSE 0.5 END"


@query("normalized_gain", with_items(f"SELECT dataset_id, round({MINMAX.format('d_mean')}, 6) AS minmax, round({MINMAX.format('d_pass')}, 6) AS minmax_pass, round(d_mean / (1 - b), 6) AS headroom, round(d_mean / b, 6) AS relative, round(d_mean / max(d_mean) OVER (), 6) AS of_max FROM ({SET_GAIN}) CROSS JOIN (SELECT round(avg(mean), 6) AS b FROM ({SOURCE_MEAN4}) WHERE model = 'base')"))
def normalized_gain(spark, sf):
    """A set's gains on a common scale, in every form."""
    base = E.mean_at_k(C.source_rollouts(spark, sf).filter("model = 'base'"), 4).select(F.col("mean_at_k").alias("b"))
    g = set_gain_mixture(spark, sf).crossJoin(F.broadcast(base))
    forms = [F.round(S.normalize_gain(g, "d_mean", how, "b"), 6).alias(name) for how, name in (("minmax", "minmax"), ("headroom", "headroom"), ("relative", "relative"), ("max", "of_max"))]
    return g.select("dataset_id", *forms, F.round(S.normalize_gain(g, "d_pass"), 6).alias("minmax_pass"))


@query("efficiency_gain", with_items(LIVE + "SELECT scale, dataset_id, s2 FROM parts"))
def efficiency_gain(spark, sf):
    return live_scores(spark, sf).select("scale", "dataset_id", "s2")


@query("capability_gain", with_items(LIVE + "SELECT scale, dataset_id, s3 FROM parts"))
def capability_gain(spark, sf):
    return live_scores(spark, sf).select("scale", "dataset_id", "s3")


@query("score_card", with_items(LIVE + "SELECT scale, dataset_id, s1, s2, s3, q, rank() OVER (PARTITION BY scale ORDER BY q DESC) AS rank FROM (SELECT *, round((0.684 - 0.363 * x) * s1 + (0.22 + 0.131 * x) * s2 + (0.096 + 0.232 * x) * s3, 6) AS q FROM parts)"))
def score_card(spark, sf):
    return S.ranked_card(live_scores(spark, sf), LIVE_CFG).select("scale", "dataset_id", "s1", "s2", "s3", "q", "rank")


ARMS = "SELECT dataset_id, arm, count(*) AS n_items, round(avg(CASE WHEN o THEN 1.0 ELSE 0.0 END), 6) AS r_mcq, round(1 - avg(CASE WHEN leaked THEN 1.0 ELSE 0.0 END), 6) AS s1c, round(1.0 * avg(CASE WHEN code IS NOT NULL THEN CASE WHEN code = '01' THEN 1.0 ELSE 0.0 END END), 6) AS p01 FROM a GROUP BY 1, 2"


@query("ablation_live", with_items(leak_sql() + f", w AS (SELECT i.dataset_id, i.item_id, {OPTION.format('prompt')} AS o, i.item_id IN (SELECT item_id FROM pairs) AS leaked, p.code FROM items i LEFT JOIN {PAIRS} p ON p.item_id = i.seq), a AS (SELECT 'original' AS arm, * FROM w UNION ALL SELECT 'cleaned', * FROM w WHERE NOT leaked UNION ALL SELECT 'without_options', * FROM w WHERE NOT o) {ARMS}"))
def ablation_live(spark, sf):
    """Both ablations on the documents: each set as it is, without leaked items, and without multiple choice."""
    rows = narrow_items(spark, sf)
    leaked = sure_pairs(spark, sf).select("item_id").distinct().withColumn("leaked", F.lit(1.0))
    verdicts = C.outcomes(spark, sf).select(F.col("item_id").alias("seq"), (A.outcome_code(F.col("base_ok"), F.col("tuned_ok")) == "01").cast("double").alias("learn"))
    every = cut(rows.join(leaked, "item_id", "left").join(verdicts, "seq", "left").select("dataset_id", F.col("options").cast("double").alias("o"), F.coalesce("leaked", F.lit(0.0)).alias("leaked"), "learn"), "arms")
    arms = every.withColumn("arm", F.lit("original")).unionByName(every.filter("leaked = 0").withColumn("arm", F.lit("cleaned"))).unionByName(every.filter("o = 0").withColumn("arm", F.lit("without_options")))
    return arms.groupBy("dataset_id", "arm").agg(F.count("*").alias("n_items"), F.round(F.avg("o"), 6).alias("r_mcq"), F.round(1 - F.avg("leaked"), 6).alias("s1c"), F.round(F.avg("learn"), 6).alias("p01"))


# Curation.
LEAST_INHERITED = "(SELECT atomic_source FROM attributed WHERE atomic_source IS NOT NULL AND stage = 'exact' GROUP BY 1 ORDER BY count(*), atomic_source LIMIT 1)"


def curation_inputs(spark, sf):
    """The set to clean, the atomic source that later sets inherited least, leaked and learnable items; pairs are found once."""
    rows = narrow_items(spark, sf)
    least = P.underused(L.attribute_keyed(rows).filter("stage = 'exact'"), 1 << 30).orderBy("n_items", "atomic_source").limit(1).select(F.col("atomic_source").alias("dataset_id"))
    mine, source = rows.filter("dataset_id = 'src19'"), rows.join(F.broadcast(least), "dataset_id", "left_semi")
    leaked = cut(sure_pairs(spark, sf).select("item_id").distinct(), "leaked")
    learn = A.learnable(C.outcomes(spark, sf)).select(F.col("item_id").cast("string").alias("item_id"))
    return mine, source, leaked, learn


POOL = f", mine AS (SELECT * FROM items WHERE dataset_id = 'src19'), leaked AS (SELECT DISTINCT item_id FROM pairs), pool AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY key ORDER BY seq) AS pr FROM items WHERE dataset_id = {LEAST_INHERITED} AND NOT {OPTION.format('prompt')} AND item_id IN (SELECT CAST(item_id AS VARCHAR) FROM {PAIRS} WHERE code = '01') AND item_id NOT IN (SELECT item_id FROM leaked) AND key NOT IN (SELECT key FROM mine)) WHERE pr = 1)"


@query("refill_pool", with_items(leak_sql() + POOL + " SELECT item_id FROM pool"))
def refill_pool(spark, sf):
    mine, source, leaked, learn = curation_inputs(spark, sf)
    return U.refill_pool(source, leaked, learn, mine).select("item_id")


CURATED = POOL + ", kept AS (SELECT item_id FROM mine WHERE item_id NOT IN (SELECT item_id FROM leaked)), added AS (SELECT item_id FROM (SELECT item_id, row_number() OVER (ORDER BY sha1('provspark:' || item_id)) AS r FROM pool) WHERE r <= (SELECT count(*) FROM mine) - (SELECT count(*) FROM kept))"


@query("curate_replace", with_items(leak_sql() + CURATED + " SELECT item_id, 'kept' AS origin FROM kept UNION ALL SELECT item_id, 'added' FROM added"))
def curate_replace(spark, sf):
    mine, source, leaked, learn = curation_inputs(spark, sf)
    out, _ = U.curate(mine, leaked, U.refill_pool(source, leaked, learn, mine), SEED)
    return out.select("item_id", "origin")


@query("base_random_refill", with_items(leak_sql() + CURATED.replace("FROM pool) WHERE r", "FROM items WHERE dataset_id = " + LEAST_INHERITED + ") WHERE r") + " SELECT item_id, 'kept' AS origin FROM kept UNION ALL SELECT item_id, 'added' FROM added"))
def base_random_refill(spark, sf):
    """Baseline: refill from the source with no conditions."""
    mine, source, leaked, _ = curation_inputs(spark, sf)
    out, _ = U.curate(mine, leaked, source, SEED)
    return out.select("item_id", "origin")


@query("curate_report", with_items(leak_sql() + CURATED + f", v AS (SELECT 'before' AS version, item_id, prompt FROM mine UNION ALL SELECT 'after', i.item_id, prompt FROM items i JOIN (SELECT item_id FROM kept UNION ALL SELECT item_id FROM added) USING (item_id)) SELECT version, count(*) AS n_items, round(avg(CASE WHEN {OPTION.format('prompt')} THEN 1.0 ELSE 0.0 END), 6) AS option_share, round(avg(CASE WHEN item_id IN (SELECT item_id FROM leaked) THEN 1.0 ELSE 0.0 END), 6) AS leak_rate FROM v GROUP BY 1"))
def curate_report(spark, sf):
    mine, source, leaked, learn = curation_inputs(spark, sf)
    out, _ = U.curate(mine, leaked, U.refill_pool(source, leaked, learn, mine), SEED)
    return U.curate_report(mine, out, leaked)


@query("curate_without_options", with_items(f"SELECT dataset_id, item_id FROM items WHERE NOT {OPTION.format('prompt')}"))
def curate_without_options(spark, sf):
    return U.drop_options(C.document_items(spark, sf)).select("dataset_id", "item_id")


def option_items(spark, sf):
    """Multiple choice made from benchmark items and part names."""
    b = C.table(spark, sf, "part")
    return b.select(F.col("p_partkey").cast("string").alias("item_id"), F.concat(F.lit("Which is it?\nA) "), "p_name", F.lit("\nB) "), "p_brand", F.lit("\nC) "), "p_type").alias("prompt"), F.element_at(F.array(F.lit("A"), F.lit("B"), F.lit("C")), (F.col("p_partkey") % 3 + 1).cast("int")).alias("answer"), F.col("p_name").alias("question"), F.array("p_name", "p_brand", "p_type").alias("options"))


@query("options_to_open", "SELECT CAST(p_partkey AS VARCHAR) AS item_id, 'Which is it?' AS open_prompt, CASE p_partkey % 3 WHEN 0 THEN p_name WHEN 1 THEN p_brand ELSE p_type END AS open_answer FROM part")
def options_to_open(spark, sf):
    return U.open_ended(option_items(spark, sf)).select("item_id", "open_prompt", "open_answer")


@query("option_shuffle", "WITH o AS (SELECT p_partkey, unnest([p_name, p_brand, p_type]) AS o, unnest([0, 1, 2]) AS i FROM part), r AS (SELECT *, row_number() OVER (PARTITION BY p_partkey ORDER BY sha1('provspark:' || p_partkey || ':' || i || ':' || o)) AS r FROM o) SELECT CAST(p_partkey AS VARCHAR) AS item_id, chr(CAST(64 + max(r) FILTER (i = p_partkey % 3) AS INT)) AS answer, string_agg(o, '|' ORDER BY r) AS options FROM r GROUP BY p_partkey")
def option_shuffle(spark, sf):
    return U.shuffle_options(option_items(spark, sf), SEED).select("item_id", "answer", F.array_join("options", "|").alias("options"))
