from pyspark.sql import functions as F

from provspark.operators import leakage as K
from provspark.plans import leak_queries as Q


def test_every_containing_pair_is_found(spark, sf):
    exact = {(r["item_id"], r["bench_item"]) for r in Q.leak_contains(spark, sf).collect()}
    found = {(r["item_id"], r["bench_item"]) for r in Q.sure_pairs(spark, sf).collect()}
    assert exact and exact <= found


def test_kinds_of_seeded_edits(spark, sf):
    kinds = {}
    for r in Q.leak_kind(spark, sf).collect():
        kinds.setdefault(r["expected"], {})[r["kind"]] = r["n"]
    for kind in ("verbatim", "formatting", "embedded", "option_transformed"):
        assert set(kinds[kind]) == {kind}
    assert "verbatim" not in kinds["rewritten"]


def test_decontaminated_sets_hold_no_leak(spark, sf):
    pairs = Q.sure_pairs(spark, sf)
    clean = K.decontaminate(Q.items(spark, sf), pairs)
    assert clean.join(pairs, ["dataset_id", "item_id"], "left_semi").count() == 0
    assert clean.count() + pairs.select("dataset_id", "item_id").distinct().count() == Q.items(spark, sf).count()


def test_candidate_strategies_recall(spark):
    got = {r["strategy"]: r for r in Q.candidate_quality(spark, "/root/testdata/sf0.01").collect()}
    assert got["hyperplane"]["recall"] >= 0.9 and got["cells"]["recall"] >= 0.9
    assert got["hyperplane"]["precision"] == got["cells"]["precision"] == 1


def test_short_and_empty_texts(spark):
    items = spark.createDataFrame([("s", "1", "one two"), ("s", "2", ""), ("s", "3", None)], "dataset_id string, item_id string, prompt string")
    bench = spark.createDataFrame([(1, "one two"), (2, "")], "item_id bigint, text string")
    assert [(r["item_id"], r["bench_item"]) for r in K.containment(items, bench).collect()] == [("1", 1)]
    assert K.windows_of(items, 3, 2).select(F.count("*")).first()[0] == 1


def test_light_rewrites_are_found_by_similarity_where_rules_fail(spark, sf):
    got = {(r["rate"], r["method"]): r["recall"] for r in Q.leak_recall(spark, sf).collect()}
    assert got[0.05, "similar_possible"] == got[0.1, "similar_possible"] == 1
    for rate in Q.RATES:
        assert got[rate, "similar_possible"] >= got[rate, "similar_sure"] and got[rate, "rule_8"] >= got[rate, "rule_13"]
    assert got[0.1, "similar_sure"] > got[0.1, "contained"] and got[0.1, "key"] == 0
    for method in ("similar_sure", "similar_possible", "rule_8", "rule_13", "contained"):
        series = [got[rate, method] for rate in Q.RATES]
        assert series == sorted(series, reverse=True)


def test_blocks_meet_all_pairs_and_ties_are_whole(spark):
    from provspark.operators import similarity as S

    rows = [(i, [float(i % 5 == j) + 0.1 * j for j in range(4)]) for i in range(40)]
    v = spark.createDataFrame(rows, "id bigint, embedding array<float>")
    one = {tuple(r) for r in S.blocked_pairs(v, v, 0.5).collect()}
    many = {tuple(r) for r in S.blocked_pairs(v, v, 0.5, block_bytes=400).collect()}
    assert one == many and one
    top = {}
    for r in S.exact_blocked(v, v, -1.0, 3, block_bytes=400).collect():
        top.setdefault(r["id"], []).append((r["rank"], r["other"]))
    best = {}
    for a, b, s in S.blocked_pairs(v, v, -1.0).collect():
        best.setdefault(a, []).append((-s, b))
    assert {k: [o for _, o in sorted(x)] for k, x in top.items()} == {k: [o for _, o in sorted(x)[:3]] for k, x in best.items()}


def test_prefixes_lose_no_pair(spark):
    from provspark.operators import similarity as S

    texts = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    t = S.term_counts(texts, "doc_id", "text")
    full = t.join(t.select(F.col("id").alias("other"), "token", F.col("weight").alias("w")), "token").filter("id <> other").groupBy("id", "other").agg(F.round(F.sum(F.col("weight") * F.col("w")), 6).alias("sim")).filter("sim >= 0.6")
    assert {tuple(r) for r in full.collect()} == {tuple(r) for r in S.prefix_pairs(t, t, 0.6).collect()}


def test_strategies_meet_in_tasks_without_a_shuffle_of_pairs(spark):
    import numpy as np

    from provspark.operators import similarity as S

    rng = np.random.default_rng(5)
    rows = [(i, [float(x) for x in rng.standard_normal(8)]) for i in range(300)] + [(300, None), (301, [0.0] * 8)]
    v = spark.createDataFrame(rows, "id bigint, embedding array<float>").selectExpr("id + 0 AS id", "embedding")
    left, right = v.filter("id % 3 <> 0"), v.filter("id % 3 = 0")
    exact = {(r["id"], r["other"]) for r in S.exact_pairs(left, right, 0.5).collect()}
    found = S.hyperplane_pairs(left, right, 0.5)
    cells = S.cell_pairs(left, right, 0.5, cells=6, probes=3)
    for pairs in (found, cells):
        got = [(r["id"], r["other"]) for r in pairs.collect()]
        assert len(got) == len(set(got)) and set(got) <= exact
        plan = pairs._jdf.queryExecution().executedPlan().toString()
        assert "Join" not in plan and "hashpartitioning" not in plan
    # Many small blocks give what one gives, also for sides of one table.
    strategies = {"hyperplane": S.hyperplane_strategy(right, 0.5), "cells": S.cell_strategy(left, right, 0.5, 6, 3)}
    one, many = (sorted(map(tuple, S.strategies_quality(left, right, 0.5, strategies, size).collect())) for size in (1 << 26, 20_000))
    assert one == many and one[0][0] == len(exact)
    slow = S.recall_at(found, S.exact_pairs(left, right, 0.5)).first()
    assert [x[:4] for x in one if x[4] == "hyperplane"] == [tuple(slow)]


def test_a_table_in_parts_has_its_own_name(spark, sf, tmp_path):
    from provspark.plans.relational_queries import scan_file_metadata

    spark.read.parquet(f"{sf}/documents.parquet").repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    for folder in (sf, tmp_path):
        assert [tuple(r) for r in scan_file_metadata(spark, str(folder)).select("file_name", "sized").distinct().collect()] == [("documents.parquet", True)]


def test_passages_are_found_wherever_they_stand(spark):
    from provspark.streaming import flows as S

    texts = ["one two three four five six", "xone two threey", "one  two", "", None, "a b", "one two three four five sixty and one two three", "two"]
    passages = ["one two three", "ne two thre", "two", "", " ", None, "e two three four five six", "one  two", "a b", "a b", "two three four five sixt"]
    docs = spark.createDataFrame([(str(i), x) for i, x in enumerate(texts)], "item_id string, prompt string")
    bench = spark.createDataFrame(list(enumerate(passages)), "bench_item bigint, t string")
    want = sorted((str(i), j) for i, x in enumerate(texts) for j, y in enumerate(passages) if x is not None and y is not None and y in x)
    for size in (1 << 20, 30):
        found = S.contained(docs, bench, size)
        assert sorted(map(tuple, found.collect())) == want
        assert "NestedLoop" not in found._jdf.queryExecution().executedPlan().toString()
