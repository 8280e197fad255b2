"""Sketches, cells and candidate pools kept up to date over streams."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import random_maps
from ..operators import greedy, kernel
from ..sources.tables import shared_folder


def files(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def sketch_stream(long: DataFrame, r: int, law: str = "sparse_sign", s: int = 3, seed: int = 0) -> DataFrame:
    """Running (row_id, k, v) of a stream of cells: a sketch is a sum over columns, so it grows by addition."""
    w = random_maps.omega(seed, F.col("col_id"), F.col("k"), law, s)
    return long.withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(r)))).withColumn("w", w).where("w != 0").groupBy("row_id", "k").agg(F.sum(F.col("value") * F.col("w")).alias("v"))


def timed(events: DataFrame, delay: str = "2 hours") -> DataFrame:
    """Events with a time zone and a watermark; later rows than ``delay`` are dropped by windows."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def cells(events: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    """(start, user_id, value): counts by window, tumbling or sliding."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(window.alias("w"), "user_id").agg(F.count("*").cast("double").alias("value")).select(F.col("w.start").alias("start"), "user_id", "value")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")


def dedup(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def enrich(events: DataFrame, dim: DataFrame, key: str) -> DataFrame:
    return events.join(dim, key, "left")


def within(a: DataFrame, b: DataFrame, key: str, span: str) -> DataFrame:
    """Rows of b that follow rows of a with the key within ``span``; both streams have watermarks on ts."""
    left = a.select(F.col(key).alias("a_key"), F.col("ts").alias("a_ts"), F.col("event_id").alias("a_id"))
    right = b.select(F.col(key).alias("b_key"), F.col("ts").alias("b_ts"), F.col("event_id").alias("b_id"))
    return left.join(right, F.expr(f"a_key = b_key AND b_ts >= a_ts AND b_ts <= a_ts + INTERVAL {span}"))


class Pool:
    """At most gamma * l columns, chosen anew for a target from the pool and each batch: a sink for foreachBatch.

    Batches come in the order of their numbers; one that was seen is skipped.
    """

    def __init__(self, l: int, target: np.ndarray | None = None, gamma: float = 2.0):
        self.size, self.l, self.target, self.last = int(np.ceil(gamma * l)), l, target, -1
        self.ids, self.x = np.empty(0, dtype=np.int64), None

    def __call__(self, batch: DataFrame, number: int) -> None:
        from ..operators.distributed import CHOSEN_DDL, _kernel

        if number <= self.last:
            return
        parts = batch.select("col_id", "vec", F.lit(0).cast("long").alias("block")).mapInArrow(_kernel(self.size, self.target, 256 << 20), CHOSEN_DDL)
        got = parts.select("col_id", "vec").collect()  # at most ``size`` columns a task
        if got:
            ids = np.concatenate([self.ids, [r.col_id for r in got]])
            x = np.array([r.vec for r in got]).T
            x = x if self.x is None else np.column_stack([self.x, x])
            ids, first = np.unique(ids, return_index=True)
            x = x[:, first]
            p = kernel.targeted(x, self.size, self.target, ids).picks
            self.ids, self.x = ids[p], x[:, p]
        self.last = number

    def selection(self, spark: SparkSession) -> DataFrame:
        if self.x is None:
            return spark.createDataFrame([], greedy.SELECTION)
        return greedy.selection(spark, self.ids, kernel.targeted(self.x, self.l, self.target, self.ids))


def run_once(frame: DataFrame, sink, checkpoint: str, mode: str = "append"):
    """Runs a stream over all that is there: into a function of batches, or a memory table of the given name."""
    writer = frame.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    query = (writer.foreachBatch(sink) if callable(sink) else writer.format("memory").queryName(sink)).start()
    query.awaitTermination()
    return query


def replay(spark: SparkSession, path: str, make, mode: str = "append", per_trigger: int = 1) -> DataFrame:
    """What a stream over the Parquet files at ``path`` has written when it has read all of them.

    make: from the stream to the frame to be written.  Results and offsets go to
    the shared folder; in complete mode each batch replaces the one before.
    """
    place = f"{shared_folder(spark)}/stream-{uuid.uuid4()}"
    # as a pattern the path may name one file or a folder
    frame = make(files(spark, f"{path[:-1]}[{path[-1]}]", spark.read.parquet(path).schema, per_trigger))

    def sink(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{place}/out/part={0 if mode == 'complete' else number}")

    run_once(frame, sink, f"{place}/offsets", mode)
    return spark.read.parquet(f"{place}/out").drop("part")


def dropped_rows(query) -> int:
    """Rows that a finished query left out as older than its watermark."""
    return sum(s["numRowsDroppedByWatermark"] for p in query.recentProgress for s in p["stateOperators"])
