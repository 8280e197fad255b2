"""Matrices as DataFrames with one row a column, their layouts and their builders."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vec

DENSE = pa.schema([("col_id", pa.int64()), ("vec", pa.list_(pa.float64()))])


@dataclass
class ColumnFrame:
    """Columns (col_id long, vec array<double>), all of ``m`` entries.

    A matrix that was made of cells also has them, (row, col_id, value) with any
    name for a row, its ids, and its columns as (col_id, idx, val): what goes by
    cells needn't have it packed.
    """

    df: DataFrame
    m: int
    cells: DataFrame | None = None
    ids: DataFrame | None = None
    sparse: DataFrame | None = None

    @property
    def spark(self):
        return self.df.sparkSession

    def names(self) -> DataFrame:
        """(col_id)."""
        return self.df.select("col_id") if self.ids is None else self.ids

    def where(self, condition) -> ColumnFrame:
        return ColumnFrame(self.df.where(condition), self.m)

    def only(self, ids: DataFrame) -> ColumnFrame:
        return ColumnFrame(self.df.join(ids, "col_id", "left_semi"), self.m)

    def validate(self) -> None:
        """Raises if a vector is null, of another length, or holds a null or non-finite entry, or an id is null or repeated."""
        bad = F.col("vec").isNull() | (F.size("vec") != self.m) | F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
        row = self.df.agg(F.count_if(F.coalesce(bad, F.lit(True))), F.count("*") - F.count("col_id")).first()
        if row[0] or row[1] or not self.df.groupBy("col_id").count().where("count > 1").isEmpty():
            raise ValueError("not a matrix: null, uneven or non-finite vectors, or ids that are null or repeated")


def from_dense(df: DataFrame, id_col: str, vec_col: str, m: int | None = None) -> ColumnFrame:
    out = df.select(F.col(id_col).cast("long").alias("col_id"), F.transform(F.col(vec_col), lambda x: x.cast("double")).alias("vec"))
    return ColumnFrame(out, m or (out.select(F.max(F.size("vec"))).first()[0] or 0))


def keys(df: DataFrame, key: str, name: str, few: int = 50_000) -> DataFrame:
    """(key, name): dense ranks from 0 of the distinct keys in order.

    Up to ``few`` keys are ranked by one task.  Beyond, ranks are numbered within ranges of keys and shifted by the ranges' sizes,
    so that no task sorts all keys.  The ranges are kept: read twice, they could
    be cut or coalesced in two ways.
    """
    distinct = df.select(F.col(key).alias("key")).where("key is not null").distinct()
    if distinct.limit(few + 1).count() <= few:
        return distinct.select("key", (F.row_number().over(Window.orderBy("key")) - 1).cast("long").alias(name))
    ranged = distinct.repartitionByRange("key").withColumn("_p", F.spark_partition_id()).persist(StorageLevel.MEMORY_AND_DISK)
    inner = ranged.withColumn("_r", F.row_number().over(Window.partitionBy("_p").orderBy("key")) - 1)
    sizes = ranged.groupBy("_p").agg(F.count("*").alias("_n"), F.min("key").alias("_k"))
    before = sizes.withColumn("_b", F.coalesce(F.sum("_n").over(Window.orderBy("_k").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return inner.join(F.broadcast(before.select("_p", "_b")), "_p").select("key", (F.col("_r") + F.col("_b")).cast("long").alias(name))


def cells(df: DataFrame, row: Column, col: Column, value: Column) -> DataFrame:
    """(row_key, col_key, value): the sum of all values of a cell."""
    return df.select(row.alias("row_key"), col.alias("col_key"), value.cast("double").alias("value")).where("row_key is not null and col_key is not null").groupBy("row_key", "col_key").agg(F.sum("value").alias("value"))


def to_long(a: ColumnFrame) -> DataFrame:
    """(row_id, col_id, value) without zeros."""
    return a.df.select("col_id", F.posexplode("vec").alias("row_id", "value")).where("value != 0").select(F.col("row_id").cast("long"), "col_id", "value")


def _scatter(m: int, most_bytes: int = 32 << 20):
    """Kernel over (col_id, idx, val): dense columns of m entries, in batches of bounded size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = max(1, most_bytes // (8 * max(m, 1)))
        for batch in batches:
            for at in range(0, batch.num_rows, step):
                part = batch.slice(at, step)
                n = pc.fill_null(pc.list_value_length(part.column(1)), 0).to_numpy()
                out = np.zeros((part.num_rows, m))
                out[np.repeat(np.arange(len(n)), n), part.column(1).flatten().to_numpy(zero_copy_only=False)] = part.column(2).flatten().to_numpy(zero_copy_only=False)
                yield pa.RecordBatch.from_arrays([part.column(0), vec.unstack(out)], schema=DENSE)

    return run


def sparse_columns(long: DataFrame, ids: DataFrame | None = None) -> DataFrame:
    """(col_id, idx, val) from (row_id, col_id, value); ``ids`` adds columns without any cell."""
    pairs = long.groupBy("col_id").agg(F.array_sort(F.collect_list(F.struct(F.col("row_id").cast("int").alias("i"), F.col("value").cast("double").alias("x")))).alias("e"))
    if ids is not None:
        pairs = ids.select("col_id").join(pairs, "col_id", "left")
    none = F.array().cast("array<struct<i:int,x:double>>")
    pairs = pairs.select(F.col("col_id").cast("long").alias("col_id"), F.coalesce("e", none).alias("e"))
    return pairs.select("col_id", F.col("e.i").alias("idx"), F.col("e.x").alias("val"))


def pack(long: DataFrame, m: int, ids: DataFrame | None = None) -> ColumnFrame:
    """Dense columns from (row_id, col_id, value), zeros where there is no cell; ``ids`` adds columns without any.

    Time and shuffle go with the cells; only the kernel at the end writes zeros.
    """
    sparse = sparse_columns(long, ids)
    return ColumnFrame(sparse.mapInArrow(_scatter(m), "col_id long, vec array<double>"), m, sparse=sparse)


def from_cells(found: DataFrame, transpose: bool = False, few: int = 200_000) -> tuple[ColumnFrame, DataFrame]:
    """(matrix, dictionary (key, col_id)) of the cells, by dense ranks of the ordered keys.

    The cells and the dictionaries are kept, since they are read more than once;
    a dictionary of up to ``few`` keys goes to the cells, which then needn't be
    shuffled for it.
    """
    found = found.persist(StorageLevel.MEMORY_AND_DISK)
    row, col = ("col_key", "row_key") if transpose else ("row_key", "col_key")
    cols, rows = (keys(found, key, name).persist(StorageLevel.MEMORY_AND_DISK) for key, name in ((col, "col_id"), (row, "row_id")))
    n, m = cols.count(), rows.count()
    near = lambda names, size, key: (F.broadcast(names) if size <= few else names).withColumnRenamed("key", key)
    placed = found.join(near(cols, n, col), col)
    packed = pack(placed.join(near(rows, m, row), row).select("row_id", "col_id", "value"), m)
    packed.cells, packed.ids = placed.select(F.col(row).alias("row"), "col_id", "value").where("row is not null and value != 0"), cols.select("col_id")
    return packed, cols


def to_sparse(a: ColumnFrame) -> DataFrame:
    """(col_id, idx, val) of the entries that aren't zero, indices in order."""
    return sparse_columns(to_long(a), a.df)


def from_sparse(df: DataFrame, m: int) -> ColumnFrame:
    """The matrix of columns (col_id, idx, val)."""
    return ColumnFrame(df.select("col_id", "idx", "val").mapInArrow(_scatter(m), "col_id long, vec array<double>"), m)


def transpose(a: ColumnFrame, n: int) -> ColumnFrame:
    return pack(to_long(a).select(F.col("col_id").alias("row_id"), F.col("row_id").alias("col_id"), "value"), n)


def duplicates(a: ColumnFrame) -> DataFrame:
    """(col_id, first_id) of columns that equal one of smaller id.

    With cells, a column is the sum of the 128-bit digests of its cells, in four
    parts and with their number; it is never packed.  Cells of zero and columns
    without any other don't count there.
    """
    if a.cells is None:
        hashed = a.df.select("col_id", F.md5(F.to_json("vec").cast("binary")).alias("h"))
    else:
        digest = F.md5(F.to_json(F.struct("row", "value")).cast("binary"))
        parts = [F.sum(F.conv(F.substring(digest, 8 * i + 1, 8), 16, 10).cast("long")).alias(f"h{i}") for i in range(4)]
        hashed = a.cells.groupBy("col_id").agg(F.count("*").alias("cells"), *parts).select("col_id", F.struct("cells", "h0", "h1", "h2", "h3").alias("h"))
    first = hashed.groupBy("h").agg(F.min("col_id").alias("first_id"), F.count("*").alias("n")).where("n > 1")
    return hashed.join(first, "h").where("col_id != first_id").select("col_id", "first_id")
