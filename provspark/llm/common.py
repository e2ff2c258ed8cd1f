"""Helpers shared by the pipeline operators: tables, shared storage, bounded Arrow slices."""

from __future__ import annotations

import re
import uuid
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Text bytes that a Python worker turns into arrays at once.
SLICE_BYTES = 4 << 20
#: Rows that cross to Python at once; the session's default of 10,000 texts costs each worker and its JVM tens of MB more.
ARROW_ROWS = 1000
#: Rows that a worker takes together at most, however short their texts are.
SLICE_ROWS = 8000
#: Rows of a table of ids or short names that may be broadcast (some 30 MB); beyond it the join is shuffled.
BROADCAST_ROWS = 500_000


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table; one in fewer pieces than there are cores is dealt out once, a larger one is left as it is."""
    table, cores = spark.read.parquet(f"{sf_dir}/{name}.parquet"), spark.sparkContext.defaultParallelism
    return table.repartition(cores) if table.rdd.getNumPartitions() < cores else table


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: the cluster's ``spark.checkpoint.dir``.

    Only where the session names none and runs in one process (tests) a folder under /tmp is used.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = "file:///tmp/provspark-shared"
    return base.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/provspark-{uuid.uuid4().hex[:12]}-{name}"


def write_read(df: DataFrame, name: str, **options: str) -> DataFrame:
    """Cut the lineage: write a table into the shared folder and read it again."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.options(**options).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.written_to = path
    return out


def if_small(table: DataFrame, rows: int) -> DataFrame:
    """A broadcast of a written table of narrow rows if it is within the bound, else the table for a shuffled join."""
    return F.broadcast(table) if rows <= BROADCAST_ROWS else table


class Scratch:
    """Tables written on the way to a result, deleted once the result itself is written."""

    def __init__(self) -> None:
        self.tables: list[DataFrame] = []

    def write(self, df: DataFrame, name: str, **options: str) -> DataFrame:
        self.tables.append(write_read(df, name, **options))
        return self.tables[-1]

    def result(self, df: DataFrame, name: str) -> DataFrame:
        out = write_read(df, name)
        for table in self.tables:
            drop_table(table)
        self.tables = []
        return out


def drop_table(df: DataFrame) -> None:
    """Delete a table made by write_read that no later step reads."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    path = jvm.org.apache.hadoop.fs.Path(df.written_to)
    path.getFileSystem(conf).delete(path, True)


def text_bytes(column: pa.Array) -> pa.Array:
    """A string or binary Arrow column as binary, nulls as empty values."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return pc.fill_null(column.cast(pa.binary()), b"")


def slices(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that the texts of a slice hold ``limit`` bytes or are one text."""
    if batch.num_rows == 0:
        return
    size = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    group = np.cumsum(size) // limit
    starts = [0, *(np.flatnonzero(np.diff(group)) + 1).tolist(), batch.num_rows]
    for a, b in zip(starts, starts[1:]):
        yield batch.slice(a, b - a)


def gathered(batches: Iterable[pa.RecordBatch], column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Batches cut and joined so that each holds some ``limit`` bytes of text, or is one text, and no more than SLICE_ROWS rows."""
    held: list[pa.RecordBatch] = []
    size = rows = 0
    for batch in batches:
        for part in slices(batch, column, limit):
            n = pc.sum(pc.binary_length(part.column(column))).as_py() or 0
            if held and (size + n > limit or rows + part.num_rows > SLICE_ROWS):
                yield one_batch(held)
                held, size, rows = [], 0, 0
            held.append(part)
            size, rows = size + n, rows + part.num_rows
    if held:
        yield one_batch(held)


def one_batch(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
    return parts[0] if len(parts) == 1 else pa.concat_batches(parts)


def map_arrow(
    df: DataFrame,
    schema: T.StructType | str,
    text: str,
    per_slice: Callable[[pa.RecordBatch], pa.RecordBatch | Iterable[pa.RecordBatch] | None],
) -> DataFrame:
    """mapInArrow over slices of bounded text size; per_slice gives one batch or some batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in gathered(batches, text):
            out = per_slice(part)
            if out is None:
                continue
            if isinstance(out, pa.RecordBatch):
                yield out
            else:
                yield from out

    return small_batches(df).mapInArrow(run, schema)


def small_batches(df: DataFrame) -> DataFrame:
    """The table, its session sending no more than ARROW_ROWS rows at once (a setting that may change at any time)."""
    conf, name = df.sparkSession.conf, "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(conf.get(name)) <= ARROW_ROWS:
        conf.set(name, str(ARROW_ROWS))
    return df


_SLOT: dict = {}


def worker_slot(key, make: Callable):
    """The one large object that a Python worker keeps between tasks; another key's object is let go first."""
    if key not in _SLOT:
        _SLOT.clear()
        _SLOT[key] = make()
    return _SLOT[key]


def as_mask(x) -> pa.Array:
    return x if isinstance(x, pa.Array) else pa.array(x, pa.bool_())


def filter_arrow(df: DataFrame, text: str, keep: Callable[[pa.RecordBatch], np.ndarray]) -> DataFrame:
    """The rows, all columns as they are, for which ``keep`` says so; no join and no shuffle."""
    return map_arrow(df, df.schema, text, lambda part: part.filter(as_mask(keep(part))))


def ragged_take(values: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Concatenate values[s : s + n] for each (s, n)."""
    total = int(lengths.sum())
    if total == 0:
        return values[:0]
    ends = np.cumsum(lengths)
    shift = np.repeat(starts - (ends - lengths), lengths)
    return values[np.arange(total) + shift]
