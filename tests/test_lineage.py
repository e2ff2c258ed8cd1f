import datetime as dt
import random

from pyspark.sql import functions as F

from provspark.operators import lineage as L
from provspark.operators import provenance as P
from provspark.operators import recovery as R

SCHEMA = "dataset_id string, dataset_no int, item_id string, released_at date, seq bigint, prompt string, answer string, meta map<string,string>"


def items(spark, rows):
    """rows: (set number, seq, prompt)."""
    return spark.createDataFrame([(f"src{n}", n, str(q), dt.date(2024, 1, 1) + dt.timedelta(30 * n), q, p, None, None) for n, q, p in rows], SCHEMA)


ROWS = [(0, 1, "a"), (5, 2, "a"), (7, 3, "a"), (7, 4, "a"), (3, 5, "b"), (6, 6, "b"), (6, 7, "c"), (8, 8, None), (8, 9, None), (8, 10, "")]


def test_attribution_plans_agree_and_null_prompts_match_nothing(spark):
    df = items(spark, ROWS)
    got = {r["item_id"]: (r["atomic_source"], r["stage"]) for r in L.attribute_exact(df).collect()}
    assert got == {r["item_id"]: (r["atomic_source"], r["stage"]) for r in L.attribute_exact(df, "window").collect()}
    assert got["2"] == got["3"] == got["4"] == ("src0", "exact")
    assert got["6"] == ("src3", "via_aggregate")
    assert got["7"][1] == got["8"][1] == got["9"][1] == got["10"][1] == "unmatched"


def test_index_does_not_depend_on_order_or_increments(spark):
    df = items(spark, ROWS)
    key = ["key", "dataset_id"]
    whole = sorted(map(tuple, L.long_index(df).orderBy(*key).collect()))
    fold = L.append_to_index(L.long_index(df.filter("dataset_no > 5")), df.filter("dataset_no <= 5"))
    assert whole == sorted(map(tuple, fold.collect()))
    assert whole == sorted(map(tuple, L.long_index(df.orderBy(F.desc("seq")).repartition(3)).collect()))


def test_predecessor_differs_from_first_on_chains(spark):
    states = L.set_states(L.keyed(items(spark, [(0, 1, "x"), (5, 2, "x"), (6, 3, "x")])))
    first = {(r["parent"], r["child"]) for r in P.contribution_edges(states).collect()}
    last = {(r["parent"], r["child"]) for r in P.contribution_edges(states, "previous").collect()}
    assert first == {("src0", "src5"), ("src0", "src6")} and last == {("src0", "src5"), ("src5", "src6")}


def test_status_counts_own_copies_as_duplicates(spark):
    got = {r["item_id"]: r["status"] for r in L.occurrence_status(items(spark, ROWS)).collect()}
    assert got["1"] == "first" and got["2"] == "repeat" and got["4"] == "duplicate" and got["8"] == "unknown"


def test_recovery_redates_and_drops_useless_candidates(spark):
    rows = [(5, 1, "a"), (5, 2, "b"), (5, 3, "c"), (1, 4, "b"), (0, 5, "a"), (2, 6, "zzz"), (3, 7, "a")]
    keys = L.keyed(items(spark, rows)).select("key", "dataset_id", "dataset_no")
    found, log = R.recover(keys, ["src3"], [["src1", "src2"], ["src0"]], tau=0.0)
    assert [x["unmatched"] for x in log] == [2, 1, 1]
    assert log[1]["kept"] == 1 and log[1]["dropped"] == 1
    assert log[2]["kept"] == 0  # it recovers nothing new and is rolled back
    assert {r["origin"] for r in found.collect()} == {"src3", "src1", "unknown"}


def test_decomposition_shares_sum_to_one(spark, sf):
    from provspark.plans.lineage_queries import source_decomposition

    for r in source_decomposition(spark, sf).groupBy("dataset_id").agg(F.sum("share").alias("s")).collect():
        assert abs(r["s"] - 1) < 1e-4


def test_index_is_one_exchange_wide_and_scans_are_pruned(spark, sf):
    from provspark.sources.carriers import document_items

    plan = L.long_index(document_items(spark, sf))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1
    assert "ReadSchema: struct<doc_id:bigint,text:string,source:string>" in plan


def test_trace_finds_rewritten_prompts_and_rounds_drop_useless_sets(spark):
    from provspark.operators import trace as T

    r = random.Random(3)
    vocab = [f"w{i}" for i in range(300)]
    prompt = lambda: " ".join(r.choice(vocab) for _ in range(40))
    up, missing, noise = [prompt() for _ in range(6)], [prompt() for _ in range(6)], [prompt() for _ in range(4)]
    rewritten = lambda t: " ".join(["please", *t.split()[:-1]])
    rows = [(0, i, t) for i, t in enumerate(up)] + [(2, 50 + i, t) for i, t in enumerate(missing)] + [(3, 70 + i, t) for i, t in enumerate(noise)]
    rows += [(9, 100 + i, rewritten(t) if i % 2 else t) for i, t in enumerate(up)] + [(9, 200 + i, rewritten(t)) for i, t in enumerate(missing)] + [(9, 300, prompt())]
    df = items(spark, rows)
    got = {x["item_id"]: (x["atomic_source"], x["stage"]) for x in T.trace(df).collect()}
    assert all(got[str(100 + i)] == ("src0", "semantic" if i % 2 else "exact") for i in range(6))
    assert all(got[str(200 + i)] == ("src2", "semantic") for i in range(6)) and got["300"] == (None, "unknown")
    found, log = T.recover_sources(df.filter("dataset_no = 9"), df, ["src0"], ["src2", "src3"], per_round=1, tau=0.0)
    assert len(log) == 3 and log[0]["unmatched"] == 7 and log[-1]["unmatched"] == 1
    assert {x["tried"]: x["kept"] for x in log[1:]} == {"src2": "src2", "src3": ""}
    assert {(x["origin"], x["stage"]) for x in found.collect()} == {("src0", "exact"), ("src0", "semantic"), ("src2", "semantic"), ("unknown", "unknown")}


def test_ancestry_lists_no_paths(spark):
    edges = spark.createDataFrame([(f"s{i}", f"s{j}") for i in range(22) for j in range(i + 1, 22)] + [(f"t{i}", f"t{i + 1}") for i in range(30)], "parent string, child string")
    got = {(x["child"], x["ancestor"]): x["depth"] for x in P.ancestry(edges).collect()}
    assert got["s21", "s0"] == 1 and got["t30", "t0"] == 30 and len(got) == 22 * 21 // 2 + 31 * 30 // 2


def test_word_count_matches_are_those_of_all_pairs(spark, monkeypatch):
    from provspark.operators import similarity as S
    from provspark.operators import wordcounts as W

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").selectExpr("doc_id AS id", "text AS prompt").withColumn("key", F.sha1(F.col("prompt").cast("binary")).cast("binary"))
    odd = spark.createDataFrame([(-1, "", b"a"), (-2, None, b"b"), (-3, " \n ", b"c"), (-4, "x", b"d"), (-4, "x", b"d")], "id bigint, prompt string, key binary")
    docs = docs.unionByName(odd)
    left, right = docs.filter("id % 2 = 0"), docs.filter("id % 3 <> 0")
    t = lambda df: S.term_counts(df.distinct(), "id", "prompt")
    exact = {(r["id"], r["other"]): r["sim"] for r in S.prefix_pairs(t(left), t(right), 0.6).collect()}
    best = {}
    for (a, b), sim in exact.items():
        best[a] = min(best.get(a, (0, 0)), (-sim, b))
    monkeypatch.setattr(W, "SLICE_CELLS", 400)
    for size in (W.BLOCK_BYTES, 40_000):
        every, first = (W.matches(W.counted(left), W.counted(right), 0.6, k, size).collect() for k in (None, 1))
        assert {(r["id"], r["other"]): r["sim"] for r in every} == exact and len(every) == len(exact) > 0
        top = {}  # a block gives its own best
        for r in first:
            top[r["id"]] = min(top.get(r["id"], (0, 0)), (-r["sim"], r["other"]))
        assert top == best and all(r["key"] and r["other_key"] for r in every)


def test_rare_words_sort_out_what_bounds_leave(monkeypatch):
    """Texts alike in frequent words alone, and ten families of copies with edits: few are compared in full, and the best are those of all pairs."""
    import numpy as np

    from provspark.operators import wordcounts as W

    monkeypatch.setattr(W, "FREQUENT", 40)
    rng, rows = np.random.default_rng(3), []
    for i in range(600):
        own = np.random.default_rng(i % 10).choice(4000, 120, replace=False) if i % 3 == 0 else rng.choice(4000, 120, replace=False)
        rows.append((np.concatenate([np.arange(40), 40 + own]) * 1_000_003 - (1 << 62), np.concatenate([rng.integers(2, 4, 40), rng.integers(1, 3, 120)])))
    tokens, counts = (np.concatenate(x) for x in zip(*rows))
    at, weights = 160 * np.arange(601), np.concatenate([c / np.sqrt((c * c).sum()) for _, c in rows])
    ids, matrix = np.arange(600) * 3 + 7, np.zeros((600, 4040))
    matrix[np.repeat(np.arange(600), 160), (tokens + (1 << 62)) // 1_000_003] = weights
    block, full, cosines = W.Block(*W.numbered(ids, at, tokens, weights)), [], W.Block.cosines
    monkeypatch.setattr(W.Block, "cosines", lambda self, cols: full.append(len(cols)) or cosines(self, cols))
    exact = np.round(matrix @ matrix.T, 6)
    np.fill_diagonal(exact, 0)
    bound = block.bounds @ block.bounds.T
    for k in (None, 1, 3):
        full.clear()
        r, other, sim = block.matches(ids, at, tokens, weights, np.full(600, 0.8), k)
        expected = {(i, int(ids[j])) for i in range(600) for j in np.lexsort((ids, -exact[i]))[: k or 600] if exact[i, j] >= 0.8}
        assert set(zip(r.tolist(), other.tolist())) == expected and len(expected) > 100 and np.allclose(sim, exact[r, (other - 7) // 3])
        assert sum(full) < 0.25 * (bound >= 0.8).sum()
    best = W.better(np.array([1, 5]), np.array([0.9, 0.95]), np.array([5, 2, 1]), np.array([0.92, 0.91, 0.99]))
    assert W.reached(np.array([5, 3, 1, 2]), *best, 0.9).tolist() == [0.95, 0.9, 0.99, 0.91]


def test_trace_writes_no_texts_and_pairs_no_words(spark):
    from provspark.operators import trace as T

    rows = [(s, 10 * s + i, f"common words of every text here {s * i % 7} " * 3 + f"own{s}{i}") for s in (0, 3, 8, 9) for i in range(10)]
    plan = T.trace(items(spark, rows))._jdf.queryExecution().executedPlan().toString()
    assert "prompt" not in plan and "token" not in plan
