"""Lineage and provenance queries on the document and order-line carriers."""

from __future__ import annotations

from pyspark.sql import functions as F

from provspark.functions.keys import LEVELS, content_key
from provspark.functions.keys import normalized as normalized_text
from provspark.operators import lineage as L
from provspark.operators import provenance as P
from provspark.plans.registry import query, with_items, with_star
from provspark.sources import carriers as C

DECLARED_SQL = "declared AS (SELECT DISTINCT dataset_id AS child, 'src' || (no % 5) AS parent FROM items WHERE role = 'training')"


def declared(items):
    """Stand-in for what sets say of their parents: each names one upstream in turn."""
    return P.training_only(items).select(F.col("dataset_id").alias("child"), F.concat(F.lit("src"), (F.col("dataset_no") % 5).cast("string")).alias("parent")).distinct()


def states(spark, sf):
    return L.set_states(L.keyed(C.document_items(spark, sf)))


def attributed(spark, sf):
    return L.attribute_exact(C.document_items(spark, sf))


@query("catalog", with_items("SELECT dataset_id, no AS dataset_no, released_at, count(*) AS n_items, role, 'type' || (no % 5) AS problem_type FROM items GROUP BY ALL"))
def catalog(spark, sf):
    return C.build_catalog(C.document_items(spark, sf))


@query("catalog_growth", "SELECT CAST(date_trunc('quarter', d) AS DATE) AS period, n, CAST(sum(n) OVER (ORDER BY date_trunc('quarter', d)) AS BIGINT) AS so_far FROM (SELECT date_trunc('quarter', DATE '2024-01-01' + CAST(30 * s AS INT)) AS d, count(*) AS n FROM (SELECT DISTINCT CAST(substr(source, 4) AS INT) AS s FROM documents) GROUP BY 1)")
def catalog_growth(spark, sf):
    return L.release_timeline(C.build_catalog(C.document_items(spark, sf)), "released_at", "quarter")


@query("catalog_growth_orders", "SELECT CAST(p AS DATE) AS period, n, CAST(sum(n) OVER (ORDER BY p) AS BIGINT) AS so_far FROM (SELECT date_trunc('month', o_orderdate) AS p, count(*) AS n FROM orders GROUP BY 1)")
def catalog_growth_orders(spark, sf):
    return L.release_timeline(C.table(spark, sf, "orders"), "o_orderdate", "month")


@query("canonical_items", with_items("SELECT dataset_id, item_id, released_at, seq, sha1(prompt) AS prompt_sha, answer FROM items UNION ALL SELECT regexp_extract(url, '://([^/:?#]+)', 1), CAST(page_id AS VARCHAR), NULL, page_id, sha1(trim(regexp_replace(regexp_replace(regexp_extract(html, '(?s)<article>(.*?)</article>', 1), '<[^>]*>', ' ', 'g'), '[ \\t\\r\\n]+', ' ', 'g'))), regexp_extract(html, '(?s)<title>(.*?)</title>', 1) FROM pages"))
def canonical_items(spark, sf):
    both = C.document_items(spark, sf).drop("meta").unionByName(C.page_items(spark, sf).drop("meta"))
    return both.select("dataset_id", "item_id", "released_at", "seq", F.sha1(F.col("prompt").cast("binary")).alias("prompt_sha"), "answer")


RULES = [(r"(?s)\n[^\n]*$", ""), (r"[ \t]+", " ")]


@query("strip_instructions", "SELECT doc_id AS seq, sha1(trim(regexp_replace(regexp_replace(text, '(?s)\\n[^\\n]*$', ''), '[ \\t]+', ' ', 'g'))) AS stripped_sha FROM documents")
def strip_instructions(spark, sf):
    out = L.strip_instructions(C.document_items(spark, sf), RULES)
    return out.select("seq", F.sha1(F.col("prompt").cast("binary")).alias("stripped_sha"))


@query("extract_qa", "SELECT conv_id, turn, text AS prompt, CASE WHEN next_role = 'assistant' THEN next_text END AS answer FROM (SELECT *, lead(role) OVER w AS next_role, lead(text) OVER w AS next_text FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'user'")
def extract_qa(spark, sf):
    return C.conversation_pairs(spark, sf)


@query("extract_qa_first_line", "SELECT doc_id, split_part(text, chr(10), 1) AS prompt, sha1(substr(text, length(split_part(text, chr(10), 1)) + 2)) AS answer_sha FROM documents")
def extract_qa_first_line(spark, sf):
    first = F.split_part("text", F.lit("\n"), F.lit(1))
    return C.table(spark, sf, "documents").select("doc_id", first.alias("prompt"), F.sha1(F.substr("text", F.length(first) + 2).cast("binary")).alias("answer_sha"))


@query("extract_qa_boxed", "SELECT doc_id, regexp_extract(text || '\\boxed{' || lang || '}', '\\\\boxed\\{([^{}]*)\\}', 1) AS answer FROM documents")
def extract_qa_boxed(spark, sf):
    """Final answers marked in the text; the documents have none, so their language is marked first."""
    marked = F.concat("text", F.lit("\\boxed{"), "lang", F.lit("}"))
    return C.table(spark, sf, "documents").select("doc_id", F.regexp_extract(marked, r"\\boxed\{([^{}]*)\}", 1).alias("answer"))


@query("inspection_sample", with_items("SELECT dataset_id, item_id, r AS rank FROM (SELECT *, CAST(row_number() OVER (PARTITION BY dataset_id ORDER BY sha1('provspark:' || item_id)) AS BIGINT) AS r FROM items) WHERE r <= 40"))
def inspection_sample(spark, sf):
    return L.inspection_sample(C.document_items(spark, sf)).select("dataset_id", "item_id", F.col("rank").cast("bigint").alias("rank"))


@query("normalize_levels", """
SELECT 'raw' AS level, count(DISTINCT text) AS n_keys FROM documents
UNION ALL SELECT 'space', count(DISTINCT trim(regexp_replace(text, '[ \\t\\r\\n]+', ' ', 'g'))) FROM documents
UNION ALL SELECT 'plain', count(DISTINCT trim(regexp_replace(regexp_replace(lower(trim(regexp_replace(text, '[ \\t\\r\\n]+', ' ', 'g'))), '[!-/:-@\\[-`{-~]+', '', 'g'), ' +', ' ', 'g'))) FROM documents
UNION ALL SELECT 'letters', count(DISTINCT regexp_replace(lower(text), '[^a-z0-9]+', '', 'g')) FROM documents""")
def normalize_levels(spark, sf):
    docs = C.table(spark, sf, "documents")
    return docs.select(F.explode(F.array(*[F.struct(F.lit(k).alias("level"), content_key(F.col("text"), k).alias("k")) for k in LEVELS])).alias("x")).groupBy("x.level").agg(F.count_distinct("x.k").alias("n_keys"))


@query("prompt_key", "SELECT doc_id, sha1(text) AS key, sha1(regexp_replace(lower(text), '[^a-z0-9]+', '', 'g')) AS letters_key FROM documents")
def prompt_key(spark, sf):
    return C.table(spark, sf, "documents").select("doc_id", content_key(F.col("text")).alias("key"), content_key(F.col("text"), "letters").alias("letters_key"))


@query("lineage_index", with_items("SELECT key, CAST(sum(n) AS BIGINT) AS n_items, count(*) AS n_sets, arg_min(dataset_id, no) AS first_dataset, CAST(arg_min(seq, no) AS VARCHAR) AS first_item, list_aggregate(list_transform(list_sort(list(no)), lambda x: 'src' || x), 'string_agg', ',') AS occurrences FROM ks GROUP BY key"))
def lineage_index(spark, sf):
    i = L.build_index(C.document_items(spark, sf))
    return i.select(L.hex_key().alias("key"), "n_items", "n_sets", F.col("first.dataset_id").alias("first_dataset"), F.col("first.item_id").alias("first_item"), F.array_join(F.col("occurrences.dataset_id"), ",").alias("occurrences"))


@query("lineage_index_star", with_star("SELECT key, CAST(sum(n) AS BIGINT) AS n_items, count(*) AS n_sets, arg_min(dataset_id, no) AS first_dataset FROM (SELECT key, dataset_id, no, count(*) AS n FROM items GROUP BY ALL) GROUP BY key"))
def lineage_index_star(spark, sf):
    i = L.build_index(C.star_items(spark, sf))
    return i.select(L.hex_key().alias("key"), "n_items", "n_sets", F.col("first.dataset_id").alias("first_dataset"))


@query("lineage_occurrences", with_items("SELECT dataset_id, item_id, CASE WHEN rn = 1 THEN 'first' WHEN row_number() OVER (PARTITION BY key, dataset_id ORDER BY seq) > 1 THEN 'duplicate' ELSE 'repeat' END AS status FROM ranked"))
def lineage_occurrences(spark, sf):
    return L.occurrence_status(C.document_items(spark, sf)).select("dataset_id", "item_id", "status")


@query("metadata_merge", with_items("SELECT key, arg_min(answer, (released_at, no, seq)) AS answer, arg_max(answer, (released_at, no, seq)) AS latest FROM items GROUP BY key"))
def metadata_merge(spark, sf):
    items = C.document_items(spark, sf)
    early, late = L.merge_metadata(items), L.merge_metadata(items, "latest").select("key", F.col("answer").alias("latest"))
    return early.join(late, "key").select(L.hex_key().alias("key"), "answer", "latest")


@query("lineage_lookup", with_items("SELECT b.item_id AS probe, f.dataset_id AS first_dataset, f.key IS NOT NULL AS known FROM (SELECT item_id, sha1(text) AS key FROM benchmark UNION ALL SELECT doc_id, sha1(text) FROM documents) b LEFT JOIN (SELECT key, dataset_id FROM ranked WHERE rn = 1) f USING (key)"))
def lineage_lookup(spark, sf):
    docs = C.table(spark, sf, "documents").select(F.col("doc_id").alias("probe"), F.col("text").alias("prompt"))
    probes = C.table(spark, sf, "benchmark").select(F.col("item_id").alias("probe"), F.col("text").alias("prompt")).unionByName(docs)
    return L.lookup(L.build_index(C.document_items(spark, sf)), probes).select("probe", "first_dataset", "known")


@query("lineage_increment", with_items("SELECT key, dataset_id, n AS n_items, seq FROM ks"))
def lineage_increment(spark, sf):
    """The index of late sets, then the earlier ones added: equal to building at once."""
    items = C.document_items(spark, sf)
    late = L.long_index(items.filter("dataset_no >= 10"))
    return L.append_to_index(late, items.filter("dataset_no < 10")).select(L.hex_key().alias("key"), "dataset_id", "n_items", "seq")


ATTRIBUTED = with_items("SELECT dataset_id, item_id, atomic_source, stage FROM attributed")


@query("exact_attribution", ATTRIBUTED)
def exact_attribution(spark, sf):
    return attributed(spark, sf).select("dataset_id", "item_id", "atomic_source", "stage")


@query("exact_attribution_window", ATTRIBUTED)
def exact_attribution_window(spark, sf):
    return L.attribute_exact(C.document_items(spark, sf), "window").select("dataset_id", "item_id", "atomic_source", "stage")


@query("unmatched", with_items("SELECT dataset_id, item_id FROM attributed WHERE atomic_source IS NULL"))
def unmatched(spark, sf):
    items = C.document_items(spark, sf)
    return L.unmatched(P.training_only(items), L.attribute_exact(items)).select("dataset_id", "item_id")


@query("unmatched_share", with_items("SELECT count(*) AS n, count(*) FILTER (atomic_source IS NULL) AS n_unmatched, round(count(*) FILTER (atomic_source IS NULL) / count(*), 6) AS share FROM attributed"))
def unmatched_share(spark, sf):
    a = attributed(spark, sf)
    return a.agg(F.count("*").alias("n"), F.count_if(F.col("atomic_source").isNull()).alias("n_unmatched")).withColumn("share", F.round(F.col("n_unmatched") / F.col("n"), 6))


@query("source_decomposition", with_items("SELECT dataset_id, coalesce(atomic_source, 'unknown') AS origin, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY dataset_id), 6) AS share FROM attributed GROUP BY 1, 2"))
def source_decomposition(spark, sf):
    return P.decompose(attributed(spark, sf))


@query("decomposition_matrix", with_items("SELECT dataset_id, " + ", ".join(f"round(count(*) FILTER (coalesce(atomic_source, 'unknown') = '{s}') / count(*), 6) AS {s}" for s in ["src0", "src1", "src2", "src3", "src4", "unknown"]) + " FROM attributed GROUP BY 1"))
def decomposition_matrix(spark, sf):
    return P.decomposition_matrix(attributed(spark, sf), ["src0", "src1", "src2", "src3", "src4", "unknown"])


TYPED = "SELECT CASE WHEN atomic_source IS NULL THEN 'unknown' ELSE 'type' || (CAST(substr(atomic_source, 4) AS INT) % 5) END AS problem_type, coalesce(atomic_source, 'unknown') AS origin, dataset_id FROM attributed"


@query("type_decomposition", with_items(f"SELECT dataset_id, problem_type AS origin, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY dataset_id), 6) AS share FROM ({TYPED}) GROUP BY 1, 2"))
def type_decomposition(spark, sf):
    return P.decompose(attributed(spark, sf), "type")


@query("type_rollup", with_items(f"SELECT problem_type, origin, count(*) AS n, CAST(grouping(problem_type, origin) AS BIGINT) AS level FROM ({TYPED}) GROUP BY ROLLUP (problem_type, origin)"))
def type_rollup(spark, sf):
    return P.type_rollup(attributed(spark, sf))


@query("geography_rollup", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def geography_rollup(spark, sf):
    """A two-level category tree on a larger table."""
    t = lambda n: C.table(spark, sf, n)
    tree = F.broadcast(t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name"))  # a fixed 25 rows
    return t("customer").select("c_nationkey").join(tree, F.col("c_nationkey") == F.col("n_nationkey")).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@query("major_sources", with_items("SELECT atomic_source, n, problem_type, dense_rank() OVER (PARTITION BY problem_type ORDER BY n DESC) AS type_rank, n >= 0.2 * sum(n) OVER () AS is_major FROM (SELECT atomic_source, 'type' || (CAST(substr(atomic_source, 4) AS INT) % 5) AS problem_type, count(*) AS n FROM attributed WHERE atomic_source IS NOT NULL GROUP BY ALL)"))
def major_sources(spark, sf):
    return P.major_sources(attributed(spark, sf), 0.2)


@query("composition_distance", with_items(", d AS (SELECT dataset_id, coalesce(atomic_source, 'unknown') AS origin, round(count(*) / sum(count(*)) OVER (PARTITION BY dataset_id), 6) AS share FROM attributed GROUP BY 1, 2), s AS (SELECT DISTINCT dataset_id FROM d) SELECT a.dataset_id AS a, b.dataset_id AS b, round(1 - coalesce((SELECT sum(least(x.share, y.share)) FROM d x JOIN d y USING (origin) WHERE x.dataset_id = a.dataset_id AND y.dataset_id = b.dataset_id), 0), 4) AS distance FROM s a JOIN s b ON a.dataset_id < b.dataset_id"))
def composition_distance(spark, sf):
    return P.composition_distance(P.decompose(attributed(spark, sf)))


@query("first_introduction", with_items("SELECT atomic_source, arg_min(dataset_id, no) AS dataset_id, min(released_at) AS released_at FROM attributed WHERE atomic_source IS NOT NULL GROUP BY 1"))
def first_introduction(spark, sf):
    return P.first_introduction(attributed(spark, sf))


FIRST_EDGES = "SELECT p AS parent, dataset_id AS child, count(*) AS n FROM (SELECT dataset_id, first_value(dataset_id) OVER (PARTITION BY key ORDER BY no) AS p FROM ks) WHERE p <> dataset_id GROUP BY ALL"
ALL_EDGES = "SELECT a.dataset_id AS parent, b.dataset_id AS child, count(*) AS n FROM ks a JOIN ks b ON a.key = b.key AND a.no < b.no GROUP BY ALL"


@query("contribution_edges", with_items(FIRST_EDGES))
def contribution_edges(spark, sf):
    return P.contribution_edges(states(spark, sf))


@query("contribution_edges_all", with_items(ALL_EDGES))
def contribution_edges_all(spark, sf):
    return P.contribution_edges(states(spark, sf), "all")


PREVIOUS_EDGES = "SELECT p AS parent, dataset_id AS child, count(*) AS n FROM (SELECT dataset_id, lag(dataset_id) OVER (PARTITION BY key ORDER BY no) AS p FROM ks) WHERE p IS NOT NULL GROUP BY ALL"


@query("base_predecessor", with_items(PREVIOUS_EDGES))
def base_predecessor(spark, sf):
    """Baseline: the origin of an item is its immediate predecessor."""
    return P.contribution_edges(states(spark, sf), "previous")


OVERLAP = "SELECT a, b, i AS inter, round(i / (na.n + nb.n - i), 6) AS jaccard, round(i / na.n, 6) AS cont_a, round(i / nb.n, 6) AS cont_b FROM (SELECT x.dataset_id AS a, y.dataset_id AS b, count(*) AS i FROM k x JOIN k y ON x.key = y.key AND x.dataset_id < y.dataset_id GROUP BY ALL) JOIN s na ON na.dataset_id = a JOIN s nb ON nb.dataset_id = b"


@query("pairwise_overlap", with_items(", k AS (SELECT DISTINCT key, dataset_id FROM items), s AS (SELECT dataset_id, count(*) AS n FROM k GROUP BY 1) " + OVERLAP))
def pairwise_overlap(spark, sf):
    return P.overlap(states(spark, sf))


@query("overlap_sketch")
def overlap_sketch(spark, sf):
    return P.overlap_sketch(states(spark, sf))


@query("inherited_items", with_items("SELECT p AS introducer, dataset_id AS heir, count(*) AS n FROM (SELECT dataset_id, first_value(dataset_id) OVER (PARTITION BY key ORDER BY no) AS p FROM ks) WHERE p <> dataset_id GROUP BY ALL"))
def inherited_items(spark, sf):
    return P.inheritance(states(spark, sf))


@query("ancestry_closure", with_items(f", e AS ({FIRST_EDGES}), up AS (SELECT child, parent AS ancestor, 1 AS depth FROM e WHERE n >= 2 UNION SELECT u.child, e.parent, u.depth + 1 FROM up u JOIN e ON e.child = u.ancestor AND e.n >= 2 WHERE u.depth < 20) SELECT child, ancestor, CAST(min(depth) AS BIGINT) AS depth FROM up GROUP BY 1, 2").replace("WITH items", "WITH RECURSIVE items", 1))
def ancestry_closure(spark, sf):
    return P.ancestry(P.contribution_edges(states(spark, sf)).filter("n >= 2"))


@query("coverage", with_items("SELECT coalesce(stage, 'all') AS stage, count(*) AS n, round(count(*) / (SELECT count(*) FROM attributed), 6) AS share FROM attributed GROUP BY ROLLUP (stage)"))
def coverage(spark, sf):
    return P.coverage(attributed(spark, sf))


@query("novelty", with_items("SELECT dataset_id, count(*) FILTER (r = 1) AS \"new\", count(*) AS total, round(count(*) FILTER (r = 1) / count(*), 6) AS share FROM (SELECT dataset_id, row_number() OVER (PARTITION BY key ORDER BY no) AS r FROM ks) GROUP BY 1"))
def novelty(spark, sf):
    return P.novelty(states(spark, sf))


@query("reuse_histogram", with_items("SELECT n AS n_sets, count(*) AS n_keys FROM (SELECT key, count(*) AS n FROM ks GROUP BY 1) GROUP BY 1"))
def reuse_histogram(spark, sf):
    return P.reuse_histogram(states(spark, sf))


@query("reuse_histogram_star", with_star("SELECT n AS n_sets, count(*) AS n_keys FROM (SELECT key, count(DISTINCT dataset_id) AS n FROM items GROUP BY 1) GROUP BY 1"))
def reuse_histogram_star(spark, sf):
    return P.reuse_histogram(L.set_states(L.keyed(C.star_items(spark, sf))))


@query("underused_sources", with_items("SELECT atomic_source, count(DISTINCT dataset_id) AS n_sets, count(*) AS n_items FROM attributed WHERE atomic_source IS NOT NULL GROUP BY 1 HAVING count(DISTINCT dataset_id) <= 5"))
def underused_sources(spark, sf):
    return P.underused(attributed(spark, sf), 5)


@query("core_upstreams", with_items(f"SELECT parent, count(*) AS n_children, CAST(sum(n) AS BIGINT) AS n_items FROM ({FIRST_EDGES}) GROUP BY 1"))
def core_upstreams(spark, sf):
    return P.core_upstreams(P.contribution_edges(states(spark, sf)))


@query("unattributed_reuse", with_items(f", {DECLARED_SQL} SELECT e.* FROM ({FIRST_EDGES}) e ANTI JOIN declared d ON e.parent = d.parent AND e.child = d.child"))
def unattributed_reuse(spark, sf):
    items = C.document_items(spark, sf)
    return P.undeclared(P.contribution_edges(states(spark, sf)), declared(items))


@query("transparency_gap", with_items(f", {DECLARED_SQL} SELECT dataset_id, round(avg(CASE WHEN d.child IS NOT NULL THEN 1.0 ELSE 0.0 END), 6) AS declared_share, round(avg(CASE WHEN atomic_source IS NOT NULL THEN 1.0 ELSE 0.0 END), 6) AS traced_share, round(avg(CASE WHEN atomic_source IS NOT NULL THEN 1.0 ELSE 0.0 END) - avg(CASE WHEN d.child IS NOT NULL THEN 1.0 ELSE 0.0 END), 6) AS gap FROM attributed a LEFT JOIN declared d ON d.child = a.dataset_id AND d.parent = a.atomic_source GROUP BY 1"))
def transparency_gap(spark, sf):
    items = C.document_items(spark, sf)
    return P.transparency(L.attribute_exact(items), declared(items))


@query("redundancy", with_items("SELECT coalesce(dataset_id, 'all') AS dataset_id, count(*) AS n_items, count(DISTINCT key) AS n_keys, round(1 - count(DISTINCT key) / count(*), 6) AS redundancy FROM items GROUP BY ROLLUP (dataset_id)"))
def redundancy(spark, sf):
    return P.redundancy(states(spark, sf))


@query("base_string_match", with_items("SELECT t.dataset_id, t.item_id, s.dataset_id AS source FROM items t JOIN items s ON t.prompt = s.prompt WHERE t.role = 'training' AND s.role <> 'training'"))
def base_string_match(spark, sf):
    """Baseline: whole strings compared in the join instead of keys; the same rows, more bytes shuffled."""
    items = C.document_items(spark, sf)
    up = items.filter("dataset_no <= 4").select("prompt", F.col("dataset_id").alias("source"))
    return P.training_only(items).join(up, "prompt").select("dataset_id", "item_id", "source")


__all__ = ["attributed", "declared", "normalized_text", "states"]
