"""The corpus pipeline: language ID, near-dedup, decontamination, mixing, token output.

Each stage takes (spark, docs, sf_dir) and gives what it keeps, written as Parquet before the next.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provspark.llm.common import drop_table, if_small, read_table, write_read
from provspark.llm.decontaminate import without_matches
from provspark.llm.langid import fit_on_documents, with_language
from provspark.llm.mixing import mix_by_source, unfolded
from provspark.llm.neardup import near_duplicates
from provspark.llm.tokens import tokens_of


def keep_identified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language that was learned; those without a letter or that nothing learned tells apart go.

    Null and empty texts go; repeated rows stay or go together; with nothing learned, documents with a letter stay.
    """
    return with_language(docs, fit_on_documents(docs))


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the least id of each group of near copies.

    Documents without an id cannot be named in a group and stay; repeated rows of one id and text become one.
    """
    kept = near_duplicates(docs).filter("kept").select(F.col("id").alias("doc_id")).distinct()
    repeated = docs.groupBy("doc_id").count().filter("count > 1 AND doc_id IS NOT NULL").select("doc_id")
    stay = docs.join(kept, "doc_id", "left_semi")
    once = stay.join(repeated, "doc_id", "left_anti")
    again = stay.join(repeated, "doc_id", "left_semi").dropDuplicates(["doc_id", "text"])
    return once.unionByName(again).unionByName(docs.filter("doc_id IS NULL")).select(docs.columns)


def drop_benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no benchmark item is found within its edit budget; null and empty texts hold none and stay."""
    return without_matches(docs, read_table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix uses it; what it does not use goes.

    Rows are told apart by all their columns, so rows without an id or with a repeated one get their own uses; rows equal in every column
    get theirs together.  Null and empty texts have no words and go; an empty table stays empty.
    """
    name = F.concat(*[F.hex(F.xxhash64(F.lit(seed), *docs.columns)) for seed in (1, 2)])
    mixed = mix_by_source(docs.withColumn("doc_id", name)).filter("size > 0")
    uses = mixed.groupBy(F.col("doc_id").alias("row_name")).agg(F.count("*").alias("rows"), (F.sum("taken") / F.first("size")).cast("bigint").alias("uses")).filter("uses > 0")
    uses = write_read(uses, "uses")
    named = docs.select(name.alias("row_name"), F.struct("*").alias("doc"))
    out = named.join(uses.filter("rows = 1"), "row_name")
    equal = uses.filter("rows > 1")
    if n := equal.count():
        out = out.unionByName(named.join(if_small(equal, n), "row_name").dropDuplicates(["row_name"]))
    return unfolded(out, "uses").select("doc.*")


def token_output(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids in Parquet files, described from the files read back: one row a document, repeated rows included, null texts as empty."""
    return tokens_of(docs)


STAGES = [
    ("language_id", keep_identified),
    ("near_dedup", keep_one_of_near_copies),
    ("decontamination", drop_benchmark_passages),
    ("mixing", mix_sources),
    ("token_output", token_output),
]

#: Language scores, edit distances and the flow are beyond SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        before, docs = docs, write_read(stage(spark, docs, sf_dir), name)
        if name != STAGES[0][0]:
            drop_table(before)
    return STAGES[-1][1](spark, docs, sf_dir)
