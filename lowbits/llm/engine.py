"""Shared plumbing: table reading, durable intermediate results, Arrow helpers, components."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.components import components as connected

_own_dir: list[str] = []

#: Rows and bytes of an Arrow batch, and bytes of input files that one shuffle partition of packed rows may stand for.
BATCH_ROWS, BATCH_BYTES, INPUT_PER_PARTITION = 1000, 8 << 20, 256 << 20


def bound_batches(spark: SparkSession) -> None:
    """Lower the rows and bytes of an Arrow batch (runtime settings): ten thousand long texts in one batch are hundreds of MB."""
    for key, most in (("maxRecordsPerBatch", BATCH_ROWS), ("maxBytesPerBatch", BATCH_BYTES)):
        key = f"spark.sql.execution.arrow.{key}"
        now = str(spark.conf.get(key)).lower()
        if not now.isdigit() or not 0 < int(now) <= most:
            spark.conf.set(key, str(most))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    bound_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; one of our own only where the session names none and all runs in one process (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _own_dir:
        _own_dir.append("file://" + tempfile.mkdtemp(prefix="lowbits-"))
    return _own_dir[0]


def stored(df: DataFrame, label: str) -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: cuts lineage, survives lost executors.

    Results read it lazily, so it stays until whoever owns the shared folder clears it."""
    spark = df.sparkSession
    bound_batches(spark)
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def same_row() -> F.Column:
    """Rows by id and text hash, (doc_id, th) against (d, t): null ids meet, different texts under one id don't."""
    return F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("th") == F.col("t"))


def partitions(spark: SparkSession, df: DataFrame | None = None) -> int:
    """Shuffle partitions of the session; more where df reads so many bytes of files that one would stand for too many."""
    bound_batches(spark)
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    if df is None:
        return parts
    leaves, size = df._jdf.queryExecution().optimizedPlan().collectLeaves(), 0
    for i in range(leaves.size()):
        known = int(str(leaves.apply(i).stats().sizeInBytes()))
        size += known if known < 1 << 60 else 0  # without statistics Spark says the greatest number there is
    return max(parts, -(-size // INPUT_PER_PARTITION))


def to_arrow_schema(schema: T.StructType) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema as convert

    return convert(schema)


def lean(fn: Callable) -> Callable:
    """A mapInArrow function that gives freed memory back when its task ends: Python workers live on between tasks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import ctypes

        pa.set_memory_pool(pa.system_memory_pool())
        yield from fn(batches)
        try:
            ctypes.CDLL("libc.so.6").malloc_trim(0)
        except OSError:  # another C library
            pass

    return run


def map_batches(df: DataFrame, fn: Callable[[pa.RecordBatch], Iterable[pa.RecordBatch]], schema: str) -> DataFrame:
    """mapInArrow with a function from one batch to batches; empty batches are skipped."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield from fn(b)

    bound_batches(df.sparkSession)
    return df.mapInArrow(lean(run), schema)


def components(edges: DataFrame, nodes: DataFrame | None = None) -> DataFrame:
    """(node, component) with 64-bit names; see the core operator."""
    ends = edges.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b"))
    return connected(ends, nodes if nodes is None else nodes.select(F.col("node").cast("long").alias("node")))
