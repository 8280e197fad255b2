"""Cross products of columns and of rows."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vec
from .matrix import ColumnFrame, to_long

PARTIAL = pa.schema([("row_id", pa.int64()), ("partial", pa.list_(pa.float64()))])
PARTIAL_DDL = "row_id long, partial array<double>"


def _by_row(a: ColumnFrame) -> DataFrame:
    """(row, col_id, value) without zeros, of the cells if the matrix has them."""
    return to_long(a).withColumnRenamed("row_id", "row") if a.cells is None else a.cells


def few_ids(a: ColumnFrame, most: int = 2048) -> np.ndarray | None:
    """The ids in order, or None if there are more than ``most``."""
    found = a.names().limit(most + 1).collect()
    return None if len(found) > most else np.array(sorted(r[0] for r in found), dtype=np.int64)


def _products(a: ColumnFrame, ids: np.ndarray, shared: bool, most_bytes: int = 32 << 20) -> DataFrame:
    """(row_id, partial): row i of the Gram matrix of the columns ``ids``, summed up by tasks over the rows that they hold.

    shared: followed by the number of rows that two columns share.
    """
    n = len(ids)
    step = max(1, most_bytes // (8 * max(n, 1)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, both, rest = np.zeros((n, n)), np.zeros((n, n)), None

        def add(rows, at, value):
            for low in range(0, int(rows[-1]) + 1, step):
                i, j = np.searchsorted(rows, (low, low + step))
                x = np.zeros((int(rows[j - 1]) - low + 1, n))
                np.add.at(x, (rows[i:j] - low, at[i:j]), value[i:j])
                np.add(total, x.T @ x, out=total)
                if shared:
                    x = (x != 0).astype(np.float64)
                    np.add(both, x.T @ x, out=both)

        for batch in batches:
            if not batch.num_rows:
                continue
            table = pa.Table.from_batches([batch] if rest is None else [rest, batch]).combine_chunks().to_batches()[0]
            ends = pc.run_end_encode(table.column(0)).run_ends.to_numpy()
            last = int(ends[-2]) if len(ends) > 1 else 0  # the row at the end may go on
            if last:
                rows = np.repeat(np.arange(len(ends) - 1), np.diff(ends[:-1], prepend=0))
                add(rows, np.searchsorted(ids, table.column(1).to_numpy()[:last]), table.column(2).to_numpy()[:last])
            rest = table.slice(last)
        if rest is not None:
            add(np.zeros(rest.num_rows, dtype=np.int64), np.searchsorted(ids, rest.column(1).to_numpy()), rest.column(2).to_numpy())
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(n)), vec.unstack(np.hstack([total, both]) if shared else total)], schema=PARTIAL)

    rows = _by_row(a).select("row", F.col("col_id").cast("long"), F.col("value").cast("double")).repartition("row").sortWithinPartitions("row")
    return vector_sums(rows.mapInArrow(run, PARTIAL_DDL), 2 * n if shared else n)


def gram_long(a: ColumnFrame) -> DataFrame:
    """(p, q, v), p <= q, of columns that share a row.

    Few columns: each task adds up the products of the rows that it holds, so
    that one matrix a task is shuffled.  Many: a self-join on the rows, with
    partial sums before the shuffle.
    """
    ids = few_ids(a)
    if ids is not None:
        n = len(ids)
        names = F.from_json(F.lit(json.dumps(ids.tolist())), "array<long>")
        rows = _products(a, ids, True).select(F.col("row_id").alias("i"), F.posexplode(F.slice("partial", 1, max(n, 1))).alias("j", "v"), F.slice("partial", n + 1, max(n, 1)).alias("both"))
        rows = rows.where("i <= j and both[j] > 0")
        return rows.select(F.get(names, F.col("i").cast("int")).alias("p"), F.get(names, "j").alias("q"), "v")
    cells = _by_row(a)
    left = cells.select("row", F.col("col_id").alias("p"), F.col("value").alias("x"))
    right = cells.select("row", F.col("col_id").alias("q"), F.col("value").alias("y"))
    return left.join(right, "row").where("p <= q").groupBy("p", "q").agg(F.sum(F.col("x") * F.col("y")).alias("v"))


def gram_local(a: ColumnFrame, most: int = 2048) -> tuple[np.ndarray, np.ndarray]:
    """(ids, Gram matrix) on the driver, of at most ``most`` columns; counted before."""
    ids = few_ids(a, most)
    if ids is None:
        raise ValueError(f"more than {most} columns")
    return ids, to_driver(_products(a, ids, False), len(ids), len(ids))


def is_tall(a: ColumnFrame, rows: int = 8192, most: int = 2048) -> bool:
    """Few columns of more rows than the driver or a kernel should hold a vector of: what can goes by the Gram matrix."""
    return a.m > rows and few_ids(a, most) is not None


def explained(g: np.ndarray, s) -> float:
    """Energy that columns s explain, from the Gram matrix."""
    s = list(s)
    return float(np.trace(np.linalg.pinv(g[np.ix_(s, s)]) @ g[s] @ g[s].T))


def accumulate(a: ColumnFrame, right, width: int) -> DataFrame:
    """(row_id, partial): a * right summed over the columns, one partial a row and task, then summed by row.

    right: a function from (ids, columns n x m) to n x width.
    """
    m = a.m

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, any_ = np.zeros((m, width)), False
        for batch in batches:
            if batch.num_rows:
                x = vec.stack(batch.column(1))
                total += x.T @ right(batch.column(0).to_numpy(), x)
                any_ = True
        if any_:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(m)), vec.unstack(total)], schema=PARTIAL)

    return vector_sums(a.df.select("col_id", "vec").mapInArrow(run, PARTIAL_DDL), width)


def vector_sums(parts: DataFrame, width: int) -> DataFrame:
    """(row_id, partial): the vectors of each row added up, as they are; one vector of a row is held at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, total = None, np.zeros(width)
        for batch in batches:
            if not batch.num_rows:
                continue
            rows, x = batch.column(0).to_numpy(), vec.stack(batch.column(1))
            first = np.flatnonzero(np.concatenate(([True], rows[1:] != rows[:-1])))
            sums, ids = np.add.reduceat(x, first, axis=0), rows[first]
            if known == ids[0]:
                sums[0] += total
            elif known is not None:
                yield pa.RecordBatch.from_arrays([pa.array([known]), vec.unstack(total[None])], schema=PARTIAL)
            if len(ids) > 1:
                yield pa.RecordBatch.from_arrays([pa.array(ids[:-1]), vec.unstack(sums[:-1])], schema=PARTIAL)
            known, total = int(ids[-1]), sums[-1]
        if known is not None:
            yield pa.RecordBatch.from_arrays([pa.array([known]), vec.unstack(total[None])], schema=PARTIAL)

    return parts.repartition("row_id").sortWithinPartitions("row_id").mapInArrow(run, PARTIAL_DDL)


def to_driver(frame: DataFrame, m: int, width: int, most_bytes: int = 512 << 20) -> np.ndarray:
    """An m x width matrix of (row_id, array), whose size is checked first."""
    if m * width * 8 > most_bytes:
        raise ValueError(f"{m} x {width} doubles don't fit the driver's budget of {most_bytes} bytes")
    out = np.zeros((m, width))
    for r in frame.collect():
        out[r[0]] = r[1]
    return out


def row_gram(a: ColumnFrame, most: int = 8192) -> np.ndarray:
    """aa', m x m, in one scan."""
    if a.m > most:
        raise ValueError(f"{a.m} rows; aa' is kept on the driver up to {most}")
    return to_driver(accumulate(a, lambda _, x: x, a.m), a.m, a.m)
