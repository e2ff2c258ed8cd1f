"""Leakage, similarity, audit and recovery queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from provspark.config import AuditPolicy
from provspark.functions.keys import band as band_of
from provspark.functions.text import hashed_shingles
from provspark.operators import audit as A
from provspark.operators import leakage as K
from provspark.operators import lineage as L
from provspark.operators import recovery as R
from provspark.operators import similarity as S
from provspark.operators import trace as T
from provspark.operators.shared import cut
from provspark.plans.registry import query, with_items, with_star
from provspark.sources import carriers as C

BENCHES = 14


def bench(spark, sf):
    return C.table(spark, sf, "benchmark").withColumn("benchmark_id", (F.col("item_id") % BENCHES).cast("int"))


def items(spark, sf):
    return C.document_items(spark, sf).select("dataset_id", "dataset_no", "item_id", "seq", "prompt")


def sure_pairs(spark, sf):
    """Pairs of documents and benchmark items at containment of 0.9 or more."""
    return K.containment(items(spark, sf), bench(spark, sf), 5, 0.9)


def split_sql(text: str) -> str:
    return f"list_filter(string_split_regex(lower({text}), '[ \\t\\r\\n]+'), lambda x: x <> '')"


def shingle_sql(w: str, n: int) -> str:
    """Shingles of a column that holds words."""
    return f"CASE WHEN len({w}) >= {n} THEN list_distinct(list_transform(range(1, len({w}) - {n - 2}), lambda i: array_to_string({w}[i:i + {n - 1}], ' '))) WHEN len({w}) > 0 THEN [array_to_string({w}, ' ')] ELSE [] END"


def leak_sql(n: int = 5, least: float = 0.9) -> str:
    """Containment pairs as ``pairs``, after the items."""
    return f""", bsh AS (SELECT item_id AS bench_item, {shingle_sql('w', n)} AS sh FROM (SELECT item_id, {split_sql('text')} AS w FROM benchmark)
), bg AS (SELECT bench_item, len(sh) AS size, unnest(sh) AS g FROM bsh
), dg AS (SELECT dataset_id, item_id, unnest(sh) AS g FROM (SELECT dataset_id, item_id, {shingle_sql('w', n)} AS sh FROM (SELECT dataset_id, item_id, {split_sql('prompt')} AS w FROM items))
), pairs AS (SELECT dataset_id, item_id, bench_item, round(count(*) / any_value(size), 6) AS similarity FROM dg JOIN bg USING (g) GROUP BY 1, 2, 3 HAVING round(count(*) / any_value(size), 6) >= {least}
), bn AS (SELECT *, item_id % 14 AS benchmark_id FROM benchmark)
"""


def leaks(sql: str) -> str:
    return with_items(leak_sql() + sql)


PLAIN = "trim(regexp_replace(regexp_replace(lower(trim(regexp_replace({0}, '[ \\t\\r\\n]+', ' ', 'g'))), '[!-/:-@\\[-`{{-~]+', '', 'g'), ' +', ' ', 'g'))"


@query("leak_exact", "SELECT source AS dataset_id, CAST(doc_id AS VARCHAR) AS item_id, item_id AS bench_item FROM documents d JOIN benchmark b ON sha1(d.text) = sha1(b.text)")
def leak_exact(spark, sf):
    return K.leak_exact(items(spark, sf), bench(spark, sf))


@query("leak_exact_levels", "SELECT 'plain' AS level, count(*) AS n FROM documents d JOIN (" + "SELECT text FROM benchmark" + f") b ON {PLAIN.format('d.text')} = {PLAIN.format('b.text')} UNION ALL SELECT 'letters', count(*) FROM documents d JOIN benchmark b ON regexp_replace(lower(d.text), '[^a-z0-9]+', '', 'g') = regexp_replace(lower(b.text), '[^a-z0-9]+', '', 'g')")
def leak_exact_levels(spark, sf):
    one = lambda level: K.leak_exact(items(spark, sf), bench(spark, sf), level).agg(F.lit(level).alias("level"), F.count("*").alias("n"))
    return one("plain").unionByName(one("letters"))


@query("leak_containment", leaks("SELECT * FROM pairs"))
def leak_containment(spark, sf):
    return sure_pairs(spark, sf)


@query("leak_contains", "SELECT source AS dataset_id, CAST(doc_id AS VARCHAR) AS item_id, item_id AS bench_item FROM documents JOIN benchmark b ON contains(documents.text, b.text)")
def leak_contains(spark, sf):
    """The exhaustive pairwise form: every text against every item, a nested loop with the small side broadcast."""
    b = bench(spark, sf).select(F.col("item_id").alias("bench_item"), F.col("text").alias("t"))
    return items(spark, sf).join(K.sized(b), F.col("prompt").contains(F.col("t"))).select("dataset_id", "item_id", "bench_item")


def sparse_leaks(spark, sf, least):
    docs = S.term_counts(C.texts(spark, sf, "documents", "doc_id", "text"), "doc_id", "text")
    b = S.term_counts(bench(spark, sf).withColumn("bid", -1 - F.col("item_id")), "bid", "text")
    return S.prefix_pairs(docs, b, least).select(F.col("id").alias("doc_id"), (-1 - F.col("other")).alias("bench_item"), "sim")


def sparse_sql(least: float) -> str:
    w = "list_filter(string_split_regex(lower(text), '[ \\t\\r\\n]+'), lambda x: x <> '')"
    return f"WITH d AS (SELECT id, t, count(*) AS n FROM (SELECT doc_id AS id, unnest({w}) AS t FROM documents) GROUP BY 1, 2), b AS (SELECT id, t, count(*) AS n FROM (SELECT item_id AS id, unnest({w}) AS t FROM benchmark) GROUP BY 1, 2), dn AS (SELECT id, sqrt(sum(n * n)) AS z FROM d GROUP BY 1), bnm AS (SELECT id, sqrt(sum(n * n)) AS z FROM b GROUP BY 1) SELECT d.id AS doc_id, b.id AS bench_item, round(sum((d.n / dn.z) * (b.n / bnm.z)), 6) AS sim FROM d JOIN b USING (t) JOIN dn ON dn.id = d.id JOIN bnm ON bnm.id = b.id GROUP BY 1, 2 HAVING round(sum((d.n / dn.z) * (b.n / bnm.z)), 6) >= {least}"


def passages_sql(least: float) -> str:
    """Best passages as ``passages``, after the items."""
    runs = "CASE WHEN len(w) >= 4 THEN list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' ')) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END"
    square = "list_sum(list_transform(list_distinct({0}), lambda e: len(list_filter({0}, lambda y: y = e)) * len(list_filter({1}, lambda y: y = e))))"
    return f""", bw AS (SELECT item_id AS bench_item, {split_sql('text')} AS w FROM benchmark
), br AS (SELECT bench_item, len(w) AS m, unnest({runs}) AS g, unnest(range(greatest(1, len(w) - 3))) AS b_at FROM bw WHERE len(w) > 0
), iw AS (SELECT dataset_id, item_id, {split_sql('prompt')} AS w FROM items
), ir AS (SELECT dataset_id, item_id, len(w) AS n, unnest({runs}) AS g, unnest(range(greatest(1, len(w) - 3))) AS p_at FROM iw WHERE len(w) > 0
), cand AS (SELECT dataset_id, item_id, bench_item, least(greatest(p_at - b_at, 0), greatest(n - m, 0)) AS at_, m FROM ir JOIN br USING (g) GROUP BY ALL HAVING count(DISTINCT b_at) >= least(2, greatest(1, m - 3))
), pq AS (SELECT dataset_id, item_id, bench_item, at_, iw.w[at_ + 1:at_ + m] AS p, bw.w AS q FROM cand JOIN iw USING (dataset_id, item_id) JOIN bw USING (bench_item)
), ps AS (SELECT dataset_id, item_id, bench_item, at_, round({square.format('p', 'q')} / (sqrt({square.format('p', 'p')}) * sqrt({square.format('q', 'q')})), 6) AS sim FROM pq
), passages AS (SELECT dataset_id, item_id, bench_item, CAST(arg_min(at_, (-sim, at_)) AS INT) AS "at", max(sim) AS sim FROM ps WHERE sim >= {least} GROUP BY 1, 2, 3
), bn AS (SELECT *, item_id % 14 AS benchmark_id FROM benchmark)
"""


def similar_leaks(spark, sf, least=0.8):
    return K.similar_windows(items(spark, sf), bench(spark, sf), least)


@query("leak_similar", with_items(passages_sql(0.8) + 'SELECT dataset_id, item_id, bench_item, "at", sim FROM passages'))
def leak_similar(spark, sf):
    """Every document against every item: its passage that is most like the item, from the possible band on."""
    return similar_leaks(spark, sf)


@query("leak_bands", with_items(passages_sql(0.7) + "SELECT CASE WHEN sim >= 0.9 THEN 'high' WHEN sim >= 0.8 THEN 'possible' ELSE 'none' END AS band, count(*) AS n FROM passages GROUP BY 1"))
def leak_bands(spark, sf):
    """How many pairs the sure band leaves out: counts by band from 0.7 on."""
    return similar_leaks(spark, sf, 0.7).groupBy(band_of(F.col("sim")).alias("band")).agg(F.count("*").alias("n"))


@query("leak_similar_whole", sparse_sql(0.55))
def leak_similar_whole(spark, sf):
    """The same with whole texts as the unit: passages inside long texts are far below the bands."""
    return sparse_leaks(spark, sf, 0.55)


W, STEP = 40, 20
WORDS_SQL = "list_filter(string_split_regex(lower(prompt), '[ \\t\\r\\n]+'), lambda x: x <> '')"


@query("leak_windows", f"""
WITH w AS (SELECT source AS dataset_id, CAST(doc_id AS VARCHAR) AS item_id, list_filter(string_split_regex(lower(text), '[ \\t\\r\\n]+'), lambda x: x <> '') AS w FROM documents
), a AS (SELECT dataset_id, item_id, w, least(s, greatest(len(w) - {W}, 0)) AS p FROM (SELECT dataset_id, item_id, w, unnest(range(0, greatest(len(w) - {W}, 0) + {STEP}, {STEP})) AS s FROM w WHERE len(w) > 0))
SELECT DISTINCT dataset_id, item_id, CAST(p AS INT) AS "at", sha1(array_to_string(w[p + 1:p + {W}], ' ')) AS window_sha FROM a""")
def leak_windows(spark, sf):
    return K.windows_of(items(spark, sf), W, STEP).select("dataset_id", "item_id", F.col("at").cast("int").alias("at"), F.sha1(F.col("window").cast("binary")).alias("window_sha"))


@query("leak_best_window", with_items(passages_sql(0.5) + 'SELECT dataset_id, item_id, bench_item, "at", sim FROM passages'))
def leak_best_window(spark, sf):
    """The best passage of all documents from half a match on, also where the text as a whole is no leak."""
    return similar_leaks(spark, sf, 0.5)


@query("leak_inclusion", leaks("SELECT dataset_id, CAST(benchmark_id AS INT) AS benchmark_id, round(h / s, 6) AS hit_share FROM (SELECT dataset_id, benchmark_id, count(DISTINCT bench_item) AS h FROM pairs JOIN bn ON bn.item_id = bench_item GROUP BY 1, 2) JOIN (SELECT benchmark_id, count(*) AS s FROM bn GROUP BY 1) USING (benchmark_id) WHERE round(h / s, 6) >= 0.3"))
def leak_inclusion(spark, sf):
    return K.bulk_inclusion(sure_pairs(spark, sf), bench(spark, sf), 0.3)


def swapped(text, rate: float):
    """A text of which about ``rate`` of the words, by a hash of their place, are other words."""
    far = lambda w, i: F.pmod(F.xxhash64(i, F.lit("edit")), F.lit(1000)) < int(rate * 1000)
    return F.array_join(F.transform(F.split(text, " "), lambda w, i: F.when(far(w, i), F.concat(F.lit("swapped"), i.cast("string"))).otherwise(w)), " ")


def edited(spark, sf):
    """Seeded edits of each benchmark passage; the set's name is the expected kind."""
    t, i = F.col("text"), F.col("item_id")
    # A light rewrite: some words replaced, the sentences in another order, other numbers.
    turned = F.array_join(F.reverse(F.split(F.regexp_replace(swapped(t, 0.06), "[0-9]", "7"), r"(?<=\\.) ")), " ")
    edits = {
        "verbatim": t,
        "formatting": F.concat(F.lit("* "), F.replace(t, F.lit(" "), F.lit("  "))),
        "embedded": F.concat(F.lit("please solve the task below now "), t, F.lit(" give the final result at last")),
        "option_transformed": F.concat(t, F.lit("\nA) one\nB) two\nC) three")),
        "rewritten": F.concat(F.lit("as follows: "), turned),
    }
    rows = C.table(spark, sf, "benchmark").filter(F.length("text") > 0)
    out = None
    for k, e in edits.items():
        part = rows.select(F.lit(k).alias("dataset_id"), i.cast("string").alias("item_id"), i.alias("seq"), e.alias("prompt"))
        out = part if out is None else out.unionByName(part)
    return out


@query("leak_kind")
def leak_kind(spark, sf):
    """Kinds found for seeded edits; the expected kind is the set's name."""
    seeded, b = cut(edited(spark, sf), "edits"), bench(spark, sf)
    pairs = K.containment(seeded, b, 5, 0.0).unionByName(K.leak_exact(seeded, b, "letters").withColumn("similarity", F.lit(1.0))).groupBy("dataset_id", "item_id", "bench_item").agg(F.max("similarity").alias("similarity"))
    near = K.similar_windows(seeded, b, 0.5).select("dataset_id", "item_id", "bench_item", F.col("sim").alias("cosine"))
    both = pairs.join(near, ["dataset_id", "item_id", "bench_item"], "full").withColumn("similarity", F.coalesce("similarity", F.lit(0.0)))
    own = both.filter(F.col("item_id") == F.col("bench_item").cast("string"))
    return K.kind_of(own, seeded, b).groupBy(F.col("dataset_id").alias("expected"), "kind").agg(F.count("*").alias("n"))


RATES = (0.0, 0.05, 0.1, 0.2, 0.3)


@query("leak_recall")
def leak_recall(spark, sf):
    """(rate, method, recall) of light rewrites: the share of edited items that each method still finds."""
    b = bench(spark, sf).filter(F.length("text") > 0)
    rows = None
    for rate in RATES:
        part = b.select(F.lit(str(rate)).alias("dataset_id"), F.col("item_id").cast("string").alias("item_id"), F.concat(F.lit("now then "), swapped(F.col("text"), rate), F.lit(" so it is")).alias("prompt"))
        rows = part if rows is None else rows.unionByName(part)
    rows = cut(rows, "rewrites")
    contained, similar = cut(K.containment(rows, b, 5, 0.9), "contained"), cut(K.similar_windows(rows, b, 0.8), "similar")
    found = {"key": K.leak_exact(rows, b, "letters"), "contained": contained, "similar_sure": similar.filter("sim >= 0.9"), "similar_possible": similar}
    for n in (13, 8):
        found[f"rule_{n}"] = K.containment(rows, b, n, 1e-9)
    total = rows.groupBy("dataset_id").agg(F.count("*").alias("total"))
    out = None
    for name, pairs in found.items():
        own = pairs.filter(F.col("item_id") == F.col("bench_item").cast("string")).groupBy("dataset_id").agg(F.count("*").alias("found"))
        part = total.join(own, "dataset_id", "left").select(F.col("dataset_id").cast("double").alias("rate"), F.lit(name).alias("method"), F.round(F.coalesce("found", F.lit(0)) / F.col("total"), 6).alias("recall"))
        out = part if out is None else out.unionByName(part)
    return out


def rule_filter_sql(n):
    w = "list_filter(string_split_regex(lower(text), '[ \\t\\r\\n]+'), lambda x: x <> '')"
    return f"WITH b AS (SELECT DISTINCT unnest({shingle_sql('w', n)}) AS g FROM (SELECT {split_sql('text')} AS w FROM benchmark)), d AS (SELECT doc_id, unnest({shingle_sql('w', n)}) AS g FROM (SELECT doc_id, {split_sql('text')} AS w FROM documents)) SELECT DISTINCT CAST(doc_id AS VARCHAR) AS item_id FROM d SEMI JOIN b USING (g)"


def rule_filter(spark, sf, n):
    b = bench(spark, sf).select(F.explode(hashed_shingles(F.col("text"), n)).alias("g")).distinct()
    mine = items(spark, sf).select("item_id", F.explode(hashed_shingles(F.col("prompt"), n)).alias("g"))
    return mine.join(b, "g", "left_semi").select("item_id").distinct()


for _n in (5, 8, 13):
    query(f"base_rule_filter_{_n}", rule_filter_sql(_n))(lambda spark, sf, n=_n: rule_filter(spark, sf, n))
query("base_rule_filter", rule_filter_sql(8))(lambda spark, sf: rule_filter(spark, sf, 8))


SEVERITY = "SELECT c.dataset_id, CAST(c.benchmark_id AS INT) AS benchmark_id, c.level, c.n, round(c.n / s.size, 6) AS rate FROM (SELECT dataset_id, benchmark_id, count(DISTINCT p.item_id) AS n, CAST(grouping(dataset_id, benchmark_id) AS BIGINT) AS level FROM {0} p JOIN bn ON bn.item_id = bench_item GROUP BY CUBE (dataset_id, benchmark_id)) c LEFT JOIN (SELECT dataset_id, count(*) AS size FROM items GROUP BY 1) s USING (dataset_id)"


@query("leak_matrix", leaks(SEVERITY.format("pairs")))
def leak_matrix(spark, sf):
    return K.severity(sure_pairs(spark, sf), items(spark, sf), bench(spark, sf))


@query("leak_matrix_sources", leaks(SEVERITY.format("(SELECT pairs.* FROM pairs WHERE CAST(substr(dataset_id, 4) AS INT) <= 4)")))
def leak_matrix_sources(spark, sf):
    """The same for upstream sources alone."""
    pairs = sure_pairs(spark, sf).filter(C.number_of(F.col("dataset_id")) <= 4)
    return K.severity(pairs, items(spark, sf), bench(spark, sf))


for _name, _least in (("leak_matrix_similar", 0.9), ("leak_matrix_possible", 0.8)):
    query(_name, with_items(passages_sql(_least) + SEVERITY.format("passages")))(lambda spark, sf, least=_least: K.severity(similar_leaks(spark, sf, least), items(spark, sf), bench(spark, sf)))


@query("decontaminate", leaks("SELECT dataset_id, item_id FROM items ANTI JOIN pairs USING (dataset_id, item_id)"))
def decontaminate(spark, sf):
    return K.decontaminate(items(spark, sf), sure_pairs(spark, sf)).select("dataset_id", "item_id")


@query("base_original_sets", with_items("SELECT dataset_id, count(*) AS n FROM items GROUP BY 1"))
def base_original_sets(spark, sf):
    """Baseline: sets as published, nothing removed."""
    return items(spark, sf).groupBy("dataset_id").agg(F.count("*").alias("n"))


@query("leak_total", leaks("SELECT dataset_id, count(*) AS n_leaked FROM (SELECT DISTINCT dataset_id, item_id FROM pairs) GROUP BY ROLLUP (dataset_id)"))
def leak_total(spark, sf):
    return K.leak_total(sure_pairs(spark, sf))


@query("leak_count", leaks("SELECT count(DISTINCT item_id) AS n_items, count(DISTINCT bench_item) AS n_bench, count(*) AS n_pairs FROM pairs"))
def leak_count(spark, sf):
    return sure_pairs(spark, sf).agg(F.count_distinct("item_id").alias("n_items"), F.count_distinct("bench_item").alias("n_bench"), F.count("*").alias("n_pairs"))


@query("leak_rate", leaks("SELECT dataset_id, round(count(DISTINCT p.item_id) / count(DISTINCT i.item_id), 6) AS leak_rate FROM items i LEFT JOIN pairs p USING (dataset_id, item_id) GROUP BY 1"))
def leak_rate(spark, sf):
    leaked = sure_pairs(spark, sf).select("dataset_id", "item_id").distinct().withColumn("l", F.lit(1.0))
    return items(spark, sf).join(leaked, ["dataset_id", "item_id"], "left").groupBy("dataset_id").agg(F.round(F.avg(F.coalesce("l", F.lit(0.0))), 6).alias("leak_rate"))


@query("leak_by_lineage", leaks("SELECT DISTINCT i.dataset_id, i.item_id, l.bench_item FROM items i JOIN (SELECT DISTINCT key, bench_item FROM pairs JOIN items USING (dataset_id, item_id)) l USING (key)"))
def leak_by_lineage(spark, sf):
    return K.spread_leaks(sure_pairs(spark, sf), L.keyed(items(spark, sf)))


# Vectors: every tenth is a "benchmark".
def vectors(spark, sf):
    return C.table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), "embedding")


def vector_sides(spark, sf):
    v = vectors(spark, sf)
    return v.filter("id % 10 <> 0"), v.filter("id % 10 = 0")


COS = "list_cosine_similarity(CAST({0}.embedding AS DOUBLE[]), CAST({1}.embedding AS DOUBLE[]))"
CUT = 0.3


@query("cosine_exact", f"SELECT a.vec_id AS id, b.vec_id AS other, round({COS.format('a', 'b')}, 6) AS sim FROM embeddings a JOIN embeddings b ON a.vec_id % 10 <> 0 AND b.vec_id % 10 = 0 WHERE {COS.format('a', 'b')} >= {CUT}")
def cosine_exact(spark, sf):
    left, right = vector_sides(spark, sf)
    return S.exact_pairs(left, right, CUT).withColumn("sim", F.round("sim", 6))


@query("semantic_topk", f"SELECT id, other, round(sim, 6) AS sim, rank FROM (SELECT a.vec_id AS id, b.vec_id AS other, {COS.format('a', 'b')} AS sim, row_number() OVER (PARTITION BY a.vec_id ORDER BY {COS.format('a', 'b')} DESC, b.vec_id) AS rank FROM embeddings a JOIN embeddings b ON a.vec_id % 10 <> 0 AND b.vec_id % 10 = 0) WHERE rank <= 5 AND sim >= 0.1")
def semantic_topk(spark, sf):
    left, right = vector_sides(spark, sf)
    return S.exact_blocked(left, right, 0.1, 5).select("id", "other", F.round("sim", 6).alias("sim"), F.col("rank").cast("bigint").alias("rank"))


@query("cosine_sparse", sparse_sql(0.5))
def cosine_sparse(spark, sf):
    return sparse_leaks(spark, sf, 0.5)


@query("cosine_lsh")
def cosine_lsh(spark, sf):
    left, right = vector_sides(spark, sf)
    return S.hyperplane_pairs(left, right, CUT, 64).withColumn("sim", F.round("sim", 6))


@query("cosine_ivf")
def cosine_ivf(spark, sf):
    left, right = vector_sides(spark, sf)
    return S.cell_pairs(left, right, CUT)


@query("cell_probes")
def cell_probes(spark, sf):
    """Recall by the number of probed cells, on the samples by which the number is chosen."""
    left, right = vector_sides(spark, sf)
    _, enough, reached = S.cell_model(left, right, CUT)
    return spark.createDataFrame([(p + 1, len(reached), round(v, 6), p + 1 == enough) for p, v in enumerate(reached)], "probes bigint, cells bigint, recall double, chosen boolean")


@query("candidate_quality")
def candidate_quality(spark, sf):
    left, right = vector_sides(spark, sf)
    return S.strategies_quality(left, right, CUT, {"hyperplane": S.hyperplane_strategy(right, CUT), "cells": S.cell_strategy(left, right, CUT)})


@query("minhash_pairs", f"WITH r AS (SELECT min(id) AS id, any_value(sh) AS sh FROM (SELECT doc_id AS id, {shingle_sql('w', 5)} AS sh FROM (SELECT doc_id, {split_sql('text')} AS w FROM documents)) WHERE len(sh) > 0 GROUP BY array_to_string(list_sort(sh), chr(10))), e AS (SELECT id, unnest(sh) AS g FROM r), c AS (SELECT id, len(sh) AS n FROM r), p AS (SELECT x.id AS a, y.id AS b, count(*) AS i FROM e x JOIN e y ON x.g = y.g AND x.id < y.id GROUP BY 1, 2) SELECT a, b, round(i / (ca.n + cb.n - i), 6) AS jaccard FROM p JOIN c ca ON ca.id = a JOIN c cb ON cb.id = b WHERE round(i / (ca.n + cb.n - i), 6) >= 0.75")
def minhash_pairs(spark, sf):
    return S.minhash_pairs(C.table(spark, sf, "documents"), "doc_id", "text", 0.75)


@query("encode_terms", sparse_sql(0.0).split(" SELECT d.id AS doc_id")[0] + " SELECT d.id, count(*) AS n_terms, round(sum(d.n / dn.z * d.n / dn.z), 6) AS norm FROM d JOIN dn USING (id) GROUP BY 1")
def encode_terms(spark, sf):
    t = S.term_counts(C.table(spark, sf, "documents"), "doc_id", "text")
    return t.groupBy("id").agg(F.count("*").alias("n_terms"), F.round(F.sum(F.col("weight") * F.col("weight")), 6).alias("norm"))


@query("encode_hashed")
def encode_hashed(spark, sf):
    return S.hashed_ngrams(C.table(spark, sf, "benchmark"), "item_id", "text").select("id", F.round(F.aggregate(F.transform("embedding", lambda x: x * x), F.lit(0.0), lambda a, x: a + x.cast("double")), 4).alias("norm"))


@query("udf_pandas_encode")
def udf_pandas_encode(spark, sf):
    def load():
        import numpy as np

        return lambda texts: np.array([[len(t), t.count(" "), t.count(".")] for t in texts], dtype=np.float32)

    return S.callable_encoder(C.table(spark, sf, "benchmark"), "item_id", "text", load)


POLICY = AuditPolicy(accept=0.35, review=0.3)
VECTOR_PAIRS = f"SELECT a.vec_id AS id, b.vec_id AS other, {COS.format('a', 'b')} AS sim, a.label = b.label AS same FROM embeddings a JOIN embeddings b ON a.vec_id % 10 <> 0 AND b.vec_id % 10 = 0 WHERE {COS.format('a', 'b')} >= 0.25"


def candidates(spark, sf):
    left, right = vector_sides(spark, sf)
    return S.exact_pairs(left, right, 0.25)


@query("audit_queue", f"SELECT id, other, round(sim, 6) AS sim, CASE WHEN (id + other) % 7 = 0 THEN 'accepted' WHEN sim >= 0.35 THEN 'accepted' WHEN sim >= 0.3 THEN 'review' ELSE 'rejected' END AS status FROM ({VECTOR_PAIRS})")
def audit_queue(spark, sf):
    """The queue with some decisions by hand (stand-ins: pairs whose ids sum to a multiple of seven)."""
    c = candidates(spark, sf)
    decisions = c.filter("(id + other) % 7 = 0").select("id", "other", F.lit("accepted").alias("decision"))
    return A.audit(c, POLICY, decisions).withColumn("sim", F.round("sim", 6))


@query("audit_winners", f"SELECT id, other, round(sim, 6) AS sim FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY sim DESC, other) AS r FROM ({VECTOR_PAIRS}) WHERE sim >= 0.35) WHERE r = 1")
def audit_winners(spark, sf):
    return A.winners(A.audit(candidates(spark, sf), POLICY), POLICY).select("id", "other", F.round("sim", 6).alias("sim"))


@query("audit_precision", f"SELECT CAST(CASE WHEN sim >= 0.65 THEN 9 ELSE floor((sim - 0.25) / 0.05) + 1 END AS BIGINT) AS band, count(*) AS n, count(*) FILTER (same) AS n_true, round(count(*) FILTER (same) / count(*), 6) AS precision FROM ({VECTOR_PAIRS}) GROUP BY 1")
def audit_precision(spark, sf):
    e = C.table(spark, sf, "embeddings")
    c = candidates(spark, sf)
    truth = c.join(e.select(F.col("vec_id").alias("id"), F.col("label").alias("x")), "id").join(e.select(F.col("vec_id").alias("other"), F.col("label").alias("y")), "other").filter("x = y")
    return A.audit_report(A.audit(c, POLICY), truth, 0.25, 0.65, 8)


@query("base_no_audit", f"SELECT count(*) AS n, round(count(*) FILTER (same) / count(*), 6) AS precision FROM ({VECTOR_PAIRS})")
def base_no_audit(spark, sf):
    """Baseline: every candidate above the threshold is taken."""
    e = C.table(spark, sf, "embeddings")
    taken = A.audit(candidates(spark, sf), AuditPolicy.accept_all(0.25)).filter("status = 'accepted'")
    both = taken.join(e.select(F.col("vec_id").alias("id"), F.col("label").alias("x")), "id").join(e.select(F.col("vec_id").alias("other"), F.col("label").alias("y")), "other")
    return both.agg(F.count("*").alias("n"), F.round(F.avg((F.col("x") == F.col("y")).cast("double")), 6).alias("precision"))


SEMANTIC_SQL = """, left_ AS (SELECT key, min(seq) AS id, any_value(prompt) AS prompt FROM attributed WHERE atomic_source IS NULL AND key IS NOT NULL GROUP BY 1
), up AS (SELECT key, min(seq) AS id, any_value(prompt) AS prompt FROM items WHERE role <> 'training' AND key IS NOT NULL GROUP BY 1
), lt AS (SELECT id, t, count(*) AS n FROM (SELECT id, unnest({w}) AS t FROM left_) GROUP BY 1, 2
), ut AS (SELECT id, t, count(*) AS n FROM (SELECT id, unnest({w}) AS t FROM up) GROUP BY 1, 2
), ln_ AS (SELECT id, sqrt(sum(n * n)) AS z FROM lt GROUP BY 1), un AS (SELECT id, sqrt(sum(n * n)) AS z FROM ut GROUP BY 1
), sp AS (SELECT lt.id AS id, ut.id AS other, round(sum((lt.n / ln_.z) * (ut.n / un.z)), 6) AS sim FROM lt JOIN ut USING (t) JOIN ln_ ON ln_.id = lt.id JOIN un ON un.id = ut.id GROUP BY 1, 2
), best AS (SELECT id, arg_min(other, (-sim, other)) AS other, max(sim) AS sim FROM sp WHERE sim >= 0.9 GROUP BY 1
), src AS (SELECT up.id AS other, coalesce(o.atom, o.aggr) AS similar_source FROM up JOIN origin o USING (key)
), traced AS (SELECT a.dataset_id, a.item_id, coalesce(a.atomic_source, s.similar_source) AS atomic_source, CASE WHEN a.atomic_source IS NOT NULL THEN a.stage WHEN s.similar_source IS NOT NULL THEN 'semantic' ELSE 'unknown' END AS stage, CASE WHEN a.atomic_source IS NULL THEN b.sim END AS sim
  FROM attributed a LEFT JOIN left_ l ON l.key = a.key LEFT JOIN best b ON b.id = l.id LEFT JOIN src s ON s.other = b.other)
""".format(w=split_sql("prompt"))


@query("semantic_attribution", with_items(SEMANTIC_SQL + "SELECT dataset_id, item_id, atomic_source, stage, sim FROM traced"))
def semantic_attribution(spark, sf):
    """Keys, then similarity under audit: the training items with the stage that found their source."""
    return T.trace(C.document_items(spark, sf)).drop("seq")


@query("coverage_stages", with_items(SEMANTIC_SQL + "SELECT stage, count(*) AS n, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM traced GROUP BY 1"))
def coverage_stages(spark, sf):
    """How much each stage attributes, and what stays unknown."""
    from pyspark.sql import Window

    n = T.trace(C.document_items(spark, sf)).groupBy("stage").agg(F.count("*").alias("n"))
    return n.withColumn("share", F.round(F.col("n") / F.sum("n").over(Window.partitionBy()), 6))


@query("base_no_semantic", with_items(SEMANTIC_SQL + "SELECT dataset_id, count(*) FILTER (stage IN ('semantic', 'unknown')) AS n_unmatched, count(*) FILTER (stage = 'unknown') AS n_with_semantic FROM traced GROUP BY 1"))
def base_no_semantic(spark, sf):
    """Baseline: what keys alone leave unmatched, beside what keys and similarity leave."""
    return T.trace(C.document_items(spark, sf)).groupBy("dataset_id").agg(F.count_if(F.col("stage").isin("semantic", "unknown")).alias("n_unmatched"), F.count_if(F.col("stage") == "unknown").alias("n_with_semantic"))


@query("recovery_rounds")
def recovery_rounds(spark, sf):
    """Rounds with both stages, audit and candidates chosen by profile: sets from src10 on are traced, the others are the repository."""
    every = C.document_items(spark, sf)
    _, log = T.recover_sources(every.filter("dataset_no >= 10"), every, ["src0"], [f"src{i}" for i in range(1, 10)], per_round=3)
    return T.rounds_table(spark, log)


def star_keys(spark, sf):
    return L.keyed(C.star_items(spark, sf)).select("key", "dataset_id", "dataset_no")


def named(a, b):
    return [f"s{i}" for i in range(a, b + 1)]


def star_recovery(spark, sf, max_rounds=None):
    return R.recover(star_keys(spark, sf), named(0, 4), [named(5, 9), named(10, 19), named(20, 39)], max_rounds=max_rounds)


STAR_LOG = """, up AS (SELECT key, min(no) AS first_no FROM items WHERE no < 40 GROUP BY 1), t AS (SELECT i.key, u.first_no FROM items i LEFT JOIN up u USING (key) WHERE no >= 40), r AS (SELECT count(*) AS total, count(*) FILTER (first_no IS NULL OR first_no >= 5) AS u0, count(*) FILTER (first_no IS NULL OR first_no >= 10) AS u1, count(*) FILTER (first_no IS NULL OR first_no >= 20) AS u2, count(*) FILTER (first_no IS NULL OR first_no >= 40) AS u3 FROM t)
SELECT 0 AS round, u0 AS unmatched FROM r UNION ALL SELECT 1, u1 FROM r WHERE u0 / total >= 0.01 UNION ALL SELECT 2, u2 FROM r WHERE u0 / total >= 0.01 AND u1 / total >= 0.01 UNION ALL SELECT 3, u3 FROM r WHERE u0 / total >= 0.01 AND u1 / total >= 0.01 AND u2 / total >= 0.01"""


@query("iterative_recovery", with_star(STAR_LOG))
def iterative_recovery(spark, sf):
    """Rounds on order lines, where recovery converges."""
    _, log = star_recovery(spark, sf)
    return R.log_table(spark, log).select(F.col("round").cast("int").alias("round"), "unmatched")


@query("unknown_label")
def unknown_label(spark, sf):
    """What each key was traced to in the end, the rest being unknown."""
    found, _ = star_recovery(spark, sf)
    return found.groupBy("origin").agg(F.count("*").alias("n_keys"), F.sum("n").alias("n_items"))


@query("base_single_pass", with_star(", up AS (SELECT DISTINCT key FROM items WHERE no < 5) SELECT count(*) FILTER (key NOT IN (SELECT key FROM up)) AS unmatched FROM items WHERE no >= 40"))
def base_single_pass(spark, sf):
    """Baseline: no recovery rounds."""
    _, log = star_recovery(spark, sf, max_rounds=0)
    return R.log_table(spark, log).select("unmatched")


@query("recovery_exhausted")
def recovery_exhausted(spark, sf):
    """Rounds on documents, which end with the candidates: most items have no upstream copy."""
    keys = L.keyed(C.document_items(spark, sf)).select("key", "dataset_id", "dataset_no")
    _, log = R.recover(keys, ["src0", "src1"], [["src2"], ["src3", "src4"]])
    return R.log_table(spark, log)


@query("format_profile", with_items("SELECT dataset_id, count(*) AS n, quantile_cont(length(prompt), 0.25) AS length_q1, quantile_cont(length(prompt), 0.5) AS length_q2, quantile_cont(length(prompt), 0.75) AS length_q3, round(avg(CASE WHEN regexp_matches(prompt, '[0-9]') THEN 1.0 ELSE 0.0 END), 6) AS digits, round(avg(CASE WHEN contains(prompt, '?') THEN 1.0 ELSE 0.0 END), 6) AS questions FROM items GROUP BY 1"))
def format_profile(spark, sf):
    return R.format_profile(items(spark, sf), ["dataset_id"]).drop("options")


@query("candidate_rank")
def candidate_rank(spark, sf):
    every = L.keyed(items(spark, sf))
    left = L.keyed(L.unmatched(C.document_items(spark, sf).filter("dataset_no > 4"), L.attribute_exact(C.document_items(spark, sf))))
    cand = every.filter("dataset_no BETWEEN 2 AND 4")
    return R.rank_candidates(left, cand, left, cand)


@query("discard_candidates", with_items("SELECT dataset_id, count(DISTINCT key) AS hits FROM items WHERE no BETWEEN 2 AND 4 AND key IN (SELECT key FROM items WHERE no > 4) GROUP BY 1"))
def discard_candidates(spark, sf):
    """Candidates that recover something; others leave the pool."""
    every = L.keyed(items(spark, sf))
    return every.filter("dataset_no BETWEEN 2 AND 4").join(every.filter("dataset_no > 4").select("key").distinct(), "key", "left_semi").groupBy("dataset_id").agg(F.count_distinct("key").alias("hits"))


@query("cost_counters")
def cost_counters(spark, sf):
    """Items keyed, shingle matches, pairs, sure pairs: what the steps of leakage cost."""
    i, b = items(spark, sf), bench(spark, sf)
    every = K.containment(i, b, 5, 0.0)
    one = lambda df, name: df.agg(F.lit(name).alias("counter"), F.count("*").alias("n"))
    return one(i, "items").unionByName(one(every, "pairs")).unionByName(one(every.filter("similarity >= 0.9"), "sure"))
