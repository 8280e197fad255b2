"""Readers and writers of tables and matrices."""

from __future__ import annotations

import re
import tempfile

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, GreaterThanOrEqual, InputPartition, LessThanOrEqual

from ..functions import random_maps, vec
from ..operators.matrix import ColumnFrame, from_dense


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only where everything runs in one process here."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        place = spark.conf.get("spark.checkpoint.dir", None)
        if not place and not re.match(r"local(\[|$)", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
        sc.setCheckpointDir(place or tempfile.mkdtemp(prefix="colpick-checkpoint-"))
    return sc.getCheckpointDir()


def write_bucketed(a: ColumnFrame, table: str, buckets: int) -> None:
    """The matrix as a table bucketed and sorted by col_id: joins and blocks by col_id then need no shuffle."""
    a.df.select("col_id", "vec").write.bucketBy(buckets, "col_id").sortBy("col_id").mode("overwrite").saveAsTable(table)


def read_columns(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """CSV, JSON lines, ORC, Parquet or text with an explicit schema."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def read_matrix(spark: SparkSession, path: str, m: int | None = None) -> ColumnFrame:
    """A matrix kept as (col_id, vec)."""
    return from_dense(spark.read.parquet(path), "col_id", "vec", m)


def write_matrix(a: ColumnFrame, path: str, blocks: int) -> None:
    """The matrix by blocks of columns: one shuffle, paid once."""
    a.df.withColumn("block", F.pmod(F.xxhash64("col_id"), F.lit(blocks)).cast("int")).repartition(blocks, "block").write.partitionBy("block").parquet(path)


def export(df: DataFrame, path: str, fmt: str = "parquet") -> None:
    writer = df.write
    writer.option("header", True).csv(path) if fmt == "csv" else writer.format(fmt).save(path)


def synthetic(spark: SparkSession, m: int, n: int, rank: int, noise: float = 0.0, seed: int = 0) -> ColumnFrame:
    """A random matrix of some rank plus noise, each column a function of its id."""
    left = random_maps.block(seed + 1, np.arange(m), rank, "gaussian")

    def run(batches):
        for b in batches:
            ids = b.column(0).to_numpy()
            x = random_maps.block(seed, ids, rank, "gaussian") @ left.T
            if noise:
                x = x + noise * random_maps.block(seed + 2, ids, m, "gaussian")
            yield pa.RecordBatch.from_arrays([b.column(0), vec.unstack(x)], names=["col_id", "vec"])

    return ColumnFrame(spark.range(n).mapInArrow(run, "col_id long, vec array<double>"), m)


class _Piece(InputPartition):
    def __init__(self, path: str, start: int, end: int):
        self.path, self.start, self.end = path, start, end


class _TripleReader(DataSourceReader):
    def __init__(self, path: str, split: int):
        self.path, self.split, self.low, self.high = path, split, None, None

    def pushFilters(self, filters):
        for f in filters:
            name = tuple(f.attribute)
            if name == ("col_id",) and isinstance(f, GreaterThanOrEqual):
                self.low = f.value
            elif name == ("col_id",) and isinstance(f, LessThanOrEqual):
                self.high = f.value
            yield f  # Spark checks again

    def partitions(self):
        import os

        size = os.path.getsize(self.path)
        return [_Piece(self.path, at, min(size, at + self.split)) for at in range(0, size, self.split)] or [_Piece(self.path, 0, 0)]

    def read(self, piece):
        with open(piece.path, "rb") as f:
            f.seek(max(0, piece.start - 1))
            if piece.start:
                f.readline()  # a line belongs to the piece that it starts in
            while f.tell() < piece.end and (line := f.readline()):
                parts = line.split()
                if len(parts) == 3 and not line.startswith(b"%"):
                    col = int(parts[1])
                    if (self.low is None or col >= self.low) and (self.high is None or col <= self.high):
                        yield int(parts[0]), col, float(parts[2])


class TripleSource(DataSource):
    """Coordinate triples "row column value" as text, read in pieces with filters on col_id applied early.

    For files that every executor can open by path; needs
    spark.sql.python.filterPushdown.enabled.
    """

    @classmethod
    def name(cls):
        return "triples"

    def schema(self):
        return "row_id long, col_id long, value double"

    def reader(self, schema):
        return _TripleReader(self.options["path"], int(self.options.get("split", 64 << 20)))
