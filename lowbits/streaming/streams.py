"""Incremental upkeep of sets and signatures with Structured Streaming.

State keeps full-width minima (they merge under union); bit planes are cut on emit.  Queries run with the
available-now trigger over the events file, so a batch of files is drained deterministically.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import hashing
from ..operators.pairs import band_rows
from ..sources.io import scratch


def source(spark: SparkSession, sf_dir: str, name: str = "events") -> DataFrame:
    """The table as a stream of files, ts as a timestamp."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in raw.columns else raw


def from_path(spark: SparkSession, path: str, schema: T.StructType, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def drain(stream: DataFrame, mode: str = "append", prepare: Callable[[DataFrame], DataFrame] | None = None, out: str | None = None, state: str | None = None) -> DataFrame:
    """Run a stream until its input is used up; the rows it emitted, as a batch table.

    complete and update modes go through foreachBatch: complete keeps the last batch, update appends.
    out, state: where rows and state go; with the same ones again, the stream resumes."""
    spark = stream.sparkSession
    out, check = out or scratch(spark, f"stream-{uuid.uuid4().hex}"), state or scratch(spark, "stream-state")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", check).outputMode("append").trigger(availableNow=True).start()
    else:

        def keep(batch: DataFrame, number: int) -> None:
            (prepare(batch) if prepare else batch).withColumn("_batch", F.lit(number)).write.mode("overwrite" if mode == "complete" else "append").parquet(out)

        q = stream.writeStream.foreachBatch(keep).option("checkpointLocation", check).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    if q.exception():
        raise RuntimeError(str(q.exception()))
    result = spark.read.parquet(out) if mode != "append" else spark.read.schema(stream.schema).parquet(out)
    return result


def signature_minima(events: DataFrame, key: str, elem: str, k: int = 16) -> DataFrame:
    """k running minima per key; repeated elements don't matter to minima, so no deduplication is needed."""
    x = events.select(key, F.col(elem).cast("long").alias("elem"))
    return x.groupBy(key).agg(*(F.min(h).alias(f"z{j}") for j, h in enumerate(hashing.family("affine31", k))))


def windowed_sets(events: DataFrame, key: str, elem: str, width: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Distinct-free counts of rows per key and window, with late rows dropped."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(w, key).agg(F.count("*").alias("n"))


def sessions(events: DataFrame, key: str, gap: str, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), key).agg(F.count("*").alias("n"))


def near_duplicate_detector(stream: DataFrame, k: int = 16, r0: float = 0.75, recall: float = 0.9) -> DataFrame:
    """Custom state: for each band key the sets that had it; emits (set_id, seen, r_hat) for sets whose minima agree in a share of r0 with an earlier one's.

    stream: set_id and z (k minima).  Bands have as many rows as a recall of ``recall`` at r0 allows.  State is an id and k
    minima for each different signature of a band key, so exact copies take one entry."""
    import numpy as np
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    rows = band_rows(r0, 1e-9, 1e-9, 31, k, recall)
    bands = F.array(*(F.concat_ws(":", F.lit(str(t)), *(F.col("z")[t * rows + i].cast("string") for i in range(rows))) for t in range(k // rows)))
    keyed = stream.select("set_id", "z", F.explode(bands).alias("band"))

    def step(key, frames, state: GroupState):
        held, flat = state.get if state.exists else ([], [])
        ids, minima = list(held), [np.asarray(flat[i * k : (i + 1) * k]) for i in range(len(held))]
        known = len(ids)
        for f in frames:
            for i, z in sorted(((int(i), np.asarray(z)[:k]) for i, z in zip(f["set_id"], f["z"])), key=lambda x: x[0]):
                share = [(z == m).mean() if j != i else -1.0 for j, m in zip(ids, minima)]
                met = next((n for n, x in enumerate(share) if x >= r0), None)
                if met is not None:
                    yield pd.DataFrame({"set_id": [i], "seen": [ids[met]], "r_hat": [float(share[met])]})
                if not any((z == m).all() for m in minima):
                    ids.append(i)
                    minima.append(z)
        if len(ids) > known:
            state.update((ids, [int(x) for m in minima for x in m]))

    return keyed.groupBy("band").applyInPandasWithState(step, "set_id long, seen long, r_hat double", "ids array<long>, minima array<long>", "append", GroupStateTimeout.NoTimeout)
