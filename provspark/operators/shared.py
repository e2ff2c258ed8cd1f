"""Tables in the folder that driver and executors share."""

from __future__ import annotations

import re
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """What ``spark.checkpoint.dir`` names; a folder under /tmp only in a session of one process that names none."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base and not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    return (base or "file:///tmp/provspark-shared").rstrip("/")


def cut(df: DataFrame, name: str) -> DataFrame:
    """Written to the shared folder and read again: plans do not grow and executors may be lost."""
    path = f"{shared_folder(df.sparkSession)}/provspark-{uuid.uuid4().hex[:12]}-{name}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Rows of keys and ids that may be sent to all workers.
FEW_ROWS = 500_000


def if_few(table: DataFrame) -> DataFrame:
    """A broadcast of a table of narrow rows if it has few (they are counted), else the table for a shuffled join."""
    return F.broadcast(table) if table.count() <= FEW_ROWS else table


def spread(df: DataFrame) -> DataFrame:
    """A table in fewer pieces than there are cores is dealt out once; one in more, as any large table, is left as it is."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


#: Rows that a Python worker receives at once.
ARROW_ROWS = 1000


def small_batches(df: DataFrame) -> DataFrame:
    """The table, its session sending no more than ARROW_ROWS rows at once (a setting that may change at any time)."""
    conf, name = df.sparkSession.conf, "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(conf.get(name)) <= ARROW_ROWS:
        conf.set(name, str(ARROW_ROWS))
    return df
