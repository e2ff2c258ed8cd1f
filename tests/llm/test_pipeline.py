import corpus_pipeline
from pyspark.sql import functions as F

from provspark.llm.decontaminate import Matcher


def test_stages_keep_clean_documents_and_drop_the_rest(spark):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["language_id", "near_dedup", "decontamination", "mixing", "token_output"]
    extra = spark.createDataFrame([(9001, None, None, "src1", 0), (9002, "123 456", None, "src1", 0), (None, docs.first()["text"], None, None, 0)], docs.schema)
    one = stages["language_id"](spark, docs.unionByName(extra), sf)
    assert one.columns == docs.columns and one.count() == docs.count() + 1
    two = stages["near_dedup"](spark, docs.unionByName(docs.limit(5)), sf)
    ids = [r["doc_id"] for r in two.collect()]
    assert len(ids) == len(set(ids)) and two.columns == docs.columns and set(ids) <= {r["doc_id"] for r in docs.collect()}
    three = stages["decontamination"](spark, docs, sf)
    match = Matcher([(r["item_id"], r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()])
    assert {r["doc_id"] for r in three.collect()} == {r["doc_id"] for r in docs.collect() if not match.matches(r["text"])}
    four = stages["mixing"](spark, docs, sf)
    total, mixed = (sum(len(r["text"].split()) for r in d.collect()) for d in (docs, four))
    longest = {}
    for r in docs.collect():
        longest[r["source"]] = max(longest.get(r["source"], 0), len(r["text"].split()))
    # Whole documents are taken: a source misses its target by less than its longest one.
    assert four.columns == docs.columns and abs(total - mixed) < sum(longest.values())
    five = stages["token_output"](spark, four, sf)
    assert five.count() == four.count()


def test_run(spark):
    assert corpus_pipeline.run(spark, "/root/testdata/sf0.001").count() > 100


def test_stages_on_odd_and_empty_tables(spark):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet").withColumn("row_name", F.lit("clash")).withColumn("uses", F.lit(7))
    odd = [(None, None, None, None, None), (7001, "", "en", "src1", 0), (7002, "word " * 30_000, "en", "src1", 5), (7002, "word " * 30_000, "en", "src1", 5), (None, "one two three", None, None, None), (None, "four five six", None, None, None)]
    odd = spark.createDataFrame([(*r, "clash", 7) for r in odd], docs.schema)
    for rows in (docs.unionByName(odd), docs.limit(0)):
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, rows, sf)
            assert name == "token_output" or out.columns == rows.columns
            n = out.count()
            assert n <= 3 * rows.count() and (rows.limit(1).count() or n == 0)
    # Rows without an id get uses of their own: the total is near the documents' own.
    mixed = dict(corpus_pipeline.STAGES)["mixing"](spark, odd, sf)
    words = sum(len((r["text"] or "").split()) for r in odd.collect())
    assert abs(sum(len(r["text"].split()) for r in mixed.collect()) - words) <= 30_000
