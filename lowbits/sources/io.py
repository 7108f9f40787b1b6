"""Table reading, round trips through file formats, and the signature store."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """df over at least as many partitions as there are cores: one small file is one split.  Large inputs stay as they are."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh path in the shared folder (spark.checkpoint.dir); a local one only where the session names none and runs in one process."""
    import tempfile
    import uuid

    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = "file://" + tempfile.gettempdir()
    return f"{base.rstrip('/')}/lowbits-{label}-{uuid.uuid4().hex}"


def written(df: DataFrame, label: str) -> tuple[DataFrame, str]:
    """(df written to the shared folder and read back, its path)."""
    path = scratch(df.sparkSession, label)
    df.write.parquet(path)
    df.sparkSession._jvm.System.gc()  # shuffle files of this step go as soon as nothing refers to them, not when the driver's heap is full
    return df.sparkSession.read.schema(df.schema).parquet(path), path


def stored(df: DataFrame, label: str) -> DataFrame:
    """df written to the shared folder and read back: computed once, lineage cut, lost executors survived."""
    return written(df, label)[0]


def remove(spark: SparkSession, path: str) -> None:
    """Delete a written folder that nothing reads any more."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def round_trip(df: DataFrame, fmt: str, path: str) -> DataFrame:
    """Write df as csv, json, orc, parquet or text and read it with its own schema (text: one string column)."""
    writer = df.write.mode("overwrite")
    if fmt == "csv":
        writer.option("header", True).csv(path)
        return df.sparkSession.read.schema(df.schema).option("header", True).csv(path)
    writer.format(fmt).save(path)
    reader = df.sparkSession.read if fmt == "text" else df.sparkSession.read.schema(df.schema)
    return reader.format(fmt).load(path)


def save_signatures(planes: DataFrame, path: str, buckets: int = 16) -> None:
    """Signature store: Parquet by bucket of set_id, sorted by set size so that size filters skip row groups."""
    from pyspark.sql import functions as F

    bucketed = planes.withColumn("bucket", F.pmod(F.xxhash64("set_id"), F.lit(buckets)).cast("int"))
    bucketed.repartition("bucket").sortWithinPartitions("bucket", "f").write.mode("overwrite").partitionBy("bucket").parquet(path)


def load_signatures(spark: SparkSession, path: str, b: int) -> DataFrame:
    """Only the planes that b bits need are read."""
    return spark.read.parquet(path).select("set_id", "f", *(f"plane_{i}" for i in range(b)))
