"""Adapters from the given tables to items: (dataset_id, dataset_no, item_id, released_at, seq, prompt, answer, meta)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from provspark.operators.shared import spread

ITEM_COLUMNS = ["dataset_id", "dataset_no", "item_id", "released_at", "seq", "prompt", "answer", "meta"]
ATOMIC, AGGREGATE, TRAINING = "atomic_source", "aggregate_source", "training"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """Columns of a table whose rows cost much work: a small one in few pieces is dealt to all cores."""
    return spread(table(spark, sf_dir, name).select(*columns))


def number_of(dataset: Column) -> Column:
    """The digits at a set's end, by which sets of one release date are ordered."""
    return F.regexp_extract(dataset, r"(\d+)$", 1).try_cast("int")


def release_of(number: Column) -> Column:
    """Stand-in for release dates, which the tables lack: thirty days a set."""
    return F.date_add(F.lit("2024-01-01").cast("date"), number * 30)


def role_of(number: Column) -> Column:
    return F.when(number <= 1, ATOMIC).when(number <= 4, AGGREGATE).otherwise(TRAINING)


def canonicalize(df: DataFrame, adapter: dict[str, Column]) -> DataFrame:
    """Project a heterogeneous table onto the item columns; columns that an adapter leaves out are null."""
    kinds = {"dataset_id": "string", "dataset_no": "int", "item_id": "string", "released_at": "date", "seq": "bigint", "prompt": "string", "answer": "string", "meta": "map<string,string>"}
    return df.select(*[adapter.get(k, F.lit(None)).cast(t).alias(k) for k, t in kinds.items()])


def document_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    no = number_of(F.col("source"))
    return canonicalize(
        texts(spark, sf_dir, "documents", "doc_id", "text", "lang", "source"),
        {"dataset_id": F.col("source"), "dataset_no": no, "item_id": F.col("doc_id"), "released_at": release_of(no), "seq": F.col("doc_id"), "prompt": F.col("text"), "answer": F.col("lang"), "meta": F.create_map(F.lit("lang"), F.col("lang"))},
    )


def star_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines as items: a supplier is a set, a part's name and size the prompt, the return flag the answer."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", F.col("l_partkey").alias("p_partkey"), "l_suppkey", "l_returnflag")
    part = table(spark, sf_dir, "part").select("p_partkey", "p_name", "p_size")
    joined = line.join(part, "p_partkey")
    return canonicalize(
        joined,
        {"dataset_id": F.concat(F.lit("s"), F.col("l_suppkey").cast("string")), "dataset_no": F.col("l_suppkey"), "item_id": F.concat_ws("-", "l_orderkey", "l_linenumber"), "released_at": release_of(F.col("l_suppkey").cast("int")), "seq": F.col("l_orderkey") * 10 + F.col("l_linenumber"), "prompt": F.concat_ws(" ", "p_name", F.col("p_size").cast("string")), "answer": F.col("l_returnflag")},
    )


def page_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    return canonicalize(pages, {"dataset_id": F.parse_url("url", F.lit("HOST")), "item_id": F.col("page_id"), "seq": F.col("page_id"), "prompt": page_text(F.col("html")), "answer": page_title(F.col("html"))})


def page_title(html: Column) -> Column:
    return F.regexp_extract(html, r"(?s)<title>(.*?)</title>", 1)


def page_text(html: Column) -> Column:
    """The text of an article element with markup dropped and white space single; references stay as written."""
    body = F.regexp_extract(html, r"(?s)<article>(.*?)</article>", 1)
    return F.trim(F.regexp_replace(F.regexp_replace(body, r"<[^>]*>", " "), r"[ \t\r\n]+", " "))


def conversation_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(conv_id, turn, prompt, answer): each user turn with the assistant turn that follows."""
    from pyspark.sql import Window

    w = Window.partitionBy("conv_id").orderBy("turn")
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.col("text").alias("prompt"), F.lead("role").over(w).alias("next_role"), F.lead("text").over(w).alias("next_text"))
    return c.filter("role = 'user'").select("conv_id", "turn", "prompt", F.when(F.col("next_role") == "assistant", F.col("next_text")).alias("answer"))


def build_catalog(items: DataFrame) -> DataFrame:
    """One row a set: role, release, size, problem type (five kinds in turn)."""
    return items.groupBy("dataset_id", "dataset_no", "released_at").agg(F.count("*").alias("n_items")).select("dataset_id", "dataset_no", "released_at", "n_items", role_of(F.col("dataset_no")).alias("role"), F.concat(F.lit("type"), (F.col("dataset_no") % 5).cast("string")).alias("problem_type"))


def outcomes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(source, item_id, base_ok, tuned_ok): stand-in for verdicts of a base model and one tuned on the item's source."""
    labels = table(spark, sf_dir, "labels").select("doc_id", F.col("toxic").alias("base_ok"), F.col("quality").alias("tuned_ok"))
    return table(spark, sf_dir, "documents").select("doc_id", "source").join(labels, "doc_id").select("source", F.col("doc_id").alias("item_id"), "base_ok", "tuned_ok")


def rollouts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(model, item, sample, reward): sampled answers with 0/1 rewards, from events."""
    e = table(spark, sf_dir, "events")
    return e.select(F.col("event_type").alias("model"), F.col("user_id").alias("item"), F.col("event_id").alias("sample"), (F.col("value") > 10).cast("int").alias("reward"))


def source_rollouts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(model, item, sample, reward) on validation items: views are the base model's answers, all other events those of the
    checkpoint tuned on one of the five upstream sources, in turn."""
    e = table(spark, sf_dir, "events")
    model = F.when(F.col("event_type") == BASE_MODEL, "base").otherwise(F.concat(F.lit("src"), (F.col("event_id") % 5).cast("string")))
    return e.select(model.alias("model"), (F.col("user_id") % 50).alias("item"), F.col("event_id").alias("sample"), (F.col("value") > 250).cast("int").alias("reward"))


BASE_MODEL = "view"


def cell_mean() -> Column:
    """The mean value of a group of events, by a sum of whole hundredths, which no order of rows changes."""
    cents = F.round(F.col("value") * 100).cast("bigint")
    return F.sum(cents) / (F.count(cents) * 100)


def results(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(scale, dataset, benchmark, value): stand-in for accuracies, the mean value of a cell of events: two scales, a base and six sets, eight benchmarks."""
    e = table(spark, sf_dir, "events")
    return e.groupBy(scale_of().alias("scale"), set_of().alias("dataset"), benchmark_of().alias("benchmark")).agg(cell_mean().alias("value"))


def scale_of() -> Column:
    return F.when(F.col("user_id") % 2 == 0, "small").otherwise("large")


def set_of() -> Column:
    n = F.col("event_id") % 7
    return F.when(n == 0, "base").otherwise(F.substr(F.lit("ABCDEF"), n.cast("int"), F.lit(1)))


def benchmark_of() -> Column:
    return F.concat(F.lit("b"), (F.expr("event_id div 7") % 8).cast("string"))


def set_averages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(scale, dataset, average) of the six sets over all benchmarks but the validation one."""
    return results(spark, sf_dir).filter((F.col("dataset") != "base") & (F.col("benchmark") != VALIDATION)).groupBy("scale", "dataset").agg(F.avg("value").alias("average"))


def set_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(scale, dataset, s1, s2, s3, q): stand-in for score parts, three shares of a set's events and their mean."""
    share = lambda c: F.count_if(c) / F.count("*")
    parts = table(spark, sf_dir, "events").groupBy(scale_of().alias("scale"), set_of().alias("dataset")).agg(share(F.col("value") <= 50).alias("s1"), share(F.col("event_type").isin("purchase", "click")).alias("s2"), share(F.col("user_id") % 3 == 0).alias("s3"))
    return parts.filter("dataset <> 'base'").withColumn("q", (F.col("s1") + F.col("s2") + F.col("s3")) / 3)


def arms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(study, subject, arm, benchmark, value): stand-in for ablations, the mean values of events with even and odd ids."""
    study = F.when(F.col("user_id") % 2 == 0, "options").otherwise("cleaning")
    subject = F.concat(F.lit("subject"), (F.col("user_id") % 3).cast("string"))
    arm = F.when(F.col("event_id") % 2 == 0, "before").otherwise("after")
    return table(spark, sf_dir, "events").groupBy(study.alias("study"), subject.alias("subject"), arm.alias("arm"), benchmark_of().alias("benchmark")).agg(cell_mean().alias("value"))


#: The benchmark of ``results`` and ``arms`` that chooses checkpoints and is no part of averages.
VALIDATION = "b0"
