"""Exact greedy selection over sparse columns when both the rows and the columns are too many for a Gram matrix.

With M = aa', a column whose residual is e scores e'Me / e'e.  A few directions v
that hold most of M, and Mv, give all of e'Me but for what M does to the part of e
outside v, which lies between 0 and the largest eigenvalue there (times that part's
energy).  So one scan of the cells gives an interval for the score of every column.
Columns whose interval reaches the best lower end are then scored exactly, by their
products with all columns, until no other interval reaches the best exact score.

That eigenvalue is bounded from above by power steps on random vectors; the bound
fails with a probability under 1e-15.  Nothing of m x m or n x n entries is formed;
the driver keeps some dozens of vectors of m entries, whose size is checked first.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vec
from . import gram, kernel

BOUNDS = pa.schema([("col_id", pa.int64()), ("low", pa.float64()), ("high", pa.float64())])


def _chunks(batches: Iterator[pa.RecordBatch], most: int = 200_000):
    """(ids, cells of each column, idx, val) of columns (col_id, idx, val), about ``most`` cells at a time."""
    for batch in batches:
        n = pc.fill_null(pc.list_value_length(batch.column(1)), 0).to_numpy()
        ends, low = np.cumsum(n), 0
        while low < len(n):
            high = max(low + 1, int(np.searchsorted(ends, (ends[low - 1] if low else 0) + most, "right")))
            part = batch.slice(low, high - low)
            yield part.column(0).to_numpy(), n[low:high], part.column(1).flatten().to_numpy(zero_copy_only=False), part.column(2).flatten().to_numpy(zero_copy_only=False)
            low = high


def _sums(count: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Sums of consecutive values, so many for each column."""
    out, live = np.zeros((len(count), *values.shape[1:])), count > 0
    if live.any():
        out[live] = np.add.reduceat(values, (np.cumsum(count) - count)[live], axis=0)
    return out


class _Scans:
    """Jobs over the sparse columns; each sends one array out and, but for the intervals, one array a task back."""

    def __init__(self, columns: DataFrame, m: int):
        self.sc, self.m = columns.sparkSession.sparkContext, m
        self.columns = columns.select("col_id", "idx", "val").persist(StorageLevel.MEMORY_AND_DISK)
        # few tasks, since each sends m x k numbers
        self.whole = self.columns.coalesce(max(1, self.sc.defaultParallelism))

    def _run(self, payload, work, schema: str, frame: DataFrame, finish=lambda df: df) -> pa.Table:
        shared = self.sc.broadcast(payload)
        try:
            return finish(frame.mapInArrow(lambda batches: work(shared.value, batches), schema)).toArrow()
        finally:
            shared.unpersist()

    def _added(self, payload, work, rows: int, width: int) -> np.ndarray:
        table = self._run(payload, work, gram.PARTIAL_DDL, self.whole, lambda df: gram.vector_sums(df, width))
        out = np.zeros((rows, width))
        if table.num_rows:
            out[table.column(0).to_numpy()] = vec.stack(table.column(1).combine_chunks())
        return out

    def energy(self) -> float:
        return float(self.columns.select(F.sum(vec.norm_sq(F.col("val")))).first()[0] or 0.0)

    def product(self, x: np.ndarray) -> np.ndarray:
        """aa'x."""

        def work(x, batches):
            total, any_ = np.zeros_like(x), False
            for _, count, idx, val in _chunks(batches):
                if len(idx):
                    parts = np.repeat(_sums(count, x[idx] * val[:, None]), count, axis=0) * val[:, None]
                    order = np.argsort(idx, kind="stable")
                    first = np.flatnonzero(np.diff(idx[order], prepend=-1))
                    total[idx[order][first]] += np.add.reduceat(parts[order], first, axis=0)
                    any_ = True
            if any_:
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), vec.unstack(total)], schema=gram.PARTIAL)

        return self._added(x, work, *x.shape)

    def captured(self, e: np.ndarray) -> np.ndarray:
        """|a'e|^2 for each column of e, summed up as it is."""

        def work(e, batches):
            total = np.zeros(e.shape[1])
            for _, count, idx, val in _chunks(batches):
                total += (_sums(count, e[idx] * val[:, None]) ** 2).sum(axis=0)
            yield pa.RecordBatch.from_arrays([pa.array([0]), vec.unstack(total[None])], schema=gram.PARTIAL)

        return self._added(e, work, 1, e.shape[1])[0]

    def intervals(self, v, z, t, q, tail: float, chosen: list[int]) -> pa.Table:
        """(col_id, low, high) of the columns whose interval of scores reaches the best lower end of their task."""

        def work(payload, batches):
            side, v_q, z_q, t = payload
            k, ids_, low_, high_ = len(t), [], [], []
            for ids, count, idx, val in _chunks(batches):
                got = _sums(count, side[idx] * val[:, None])
                w, g0 = got[:, 2 * k :], _sums(count, val * val)
                alpha, y = got[:, :k] - w @ v_q.T, got[:, k : 2 * k] - w @ z_q.T
                g = g0 - (w * w).sum(axis=1)
                alive = (g > kernel.DEAD * g0) & (g > 0) & ~np.isin(ids, chosen)
                low = 2 * (alpha * y).sum(axis=1) - ((alpha @ t) * alpha).sum(axis=1)
                high = low + tail * np.maximum(g - (alpha * alpha).sum(axis=1), 0)
                ids_.append(ids[alive])
                low_.append(low[alive] / g[alive])
                high_.append(high[alive] / g[alive])
            if sum(map(len, ids_)):
                ids, low, high = (np.concatenate(x) for x in (ids_, low_, high_))
                at = high >= low.max() - 1e-6 * abs(low.max())
                yield pa.RecordBatch.from_arrays([pa.array(ids[at]), pa.array(low[at]), pa.array(high[at])], schema=BOUNDS)

        return self._run((np.hstack([v, z, q]), v.T @ q, z.T @ q, t), work, "col_id long, low double, high double", self.columns)

    def dense(self, ids) -> np.ndarray:
        """m x len(ids): the named columns."""
        at, out = {int(i): p for p, i in enumerate(ids)}, np.zeros((self.m, len(ids)))
        table = self.columns.where(F.col("col_id").isin(list(at))).toArrow()
        for i, idx, val in zip(table.column(0).to_pylist(), table.column(1), table.column(2)):
            out[idx.values.to_numpy(zero_copy_only=False), at[i]] = val.values.to_numpy(zero_copy_only=False)
        return out


def directions(scans: _Scans, k: int, seed: int = 0) -> tuple[np.ndarray, np.ndarray, float]:
    """(v, aa'v, bound): orthonormal leading directions, and a bound on the largest eigenvalue of aa' outside them."""
    rng, m = np.random.default_rng(seed), scans.m
    k = min(k, m)
    v = np.linalg.qr(rng.normal(size=(m, k)))[0]
    for _ in range(3):
        v = np.linalg.qr(scans.product(v))[0]
    # with probability 1 - 80 ** -8 or more no vector's growth falls short of the norm by more than the factor
    # the bound has that factor's root of so many steps: 1.42 with 12
    tries, steps, factor = 8, 12, 80 * math.sqrt(2 / math.pi)
    x, z, scale = rng.normal(size=(m, tries)), None, 0.0
    for step in range(steps):
        x -= v @ (v.T @ x)
        got = scans.product(np.hstack([v, x]) if step == 0 else x)
        if step == 0:
            z, got = got[:, :k], got[:, k:]
        x = got - v @ (v.T @ got)
        size = float(np.linalg.norm(x, axis=0).max())
        if not size:
            return v, z, 0.0
        x, scale = x / size, scale + math.log(size)
    return v, z, math.exp((scale + math.log(factor)) / steps)


def sparse_select(columns: DataFrame, m: int, l: int, digits: int = 9, batch: int = 32, most_bytes: int = 256 << 20) -> DataFrame:
    """The columns of :func:`greedy.greedy_select` for columns (col_id, idx, val) of m entries."""
    from .greedy import selection

    k = min(32, (most_bytes // (8 * max(m, 1)) - l) // 2)
    if k < min(4, m):
        raise ValueError(f"vectors of {m} entries exceed the driver's budget of {most_bytes} bytes")
    scans, spark = _Scans(columns, m), columns.sparkSession
    energy = left = scans.energy()
    v, z, tail = directions(scans, k)
    t, q = (v.T @ z + z.T @ v) / 2, np.zeros((m, 0))
    trace, ids = kernel.Trace(), []
    size = max(1, min(batch, most_bytes // (16 * m)))
    while len(ids) < l:
        table = scans.intervals(v, z, t, q, tail, ids)
        if not table.num_rows:
            break
        names, low, high = (table.column(i).to_numpy() for i in range(3))
        slack = 1e-9 * energy  # rounding of the intervals
        order = np.lexsort((names, -high))
        order = order[high[order] >= low.max() - slack]
        found: list[tuple[float, int, np.ndarray]] = []
        for at in range(0, len(order), size):
            best = max((s for s, *_ in found), default=0.0)
            part = order[at : at + size]
            if found and high[part[0]] + slack < best * (1 - 10.0**-digits):
                break
            e = scans.dense(names[part])
            for _ in range(2):
                e -= q @ (q.T @ e)
            own = (e * e).sum(axis=0)
            score = scans.captured(e) / own
            best = max(best, float(score.max()))
            found = [f for f in found if f[0] >= best * (1 - 10.0**-digits)]
            found += [(float(score[p]), int(names[i]), e[:, p] / math.sqrt(own[p])) for p, i in enumerate(part) if score[p] >= best * (1 - 10.0**-digits)]
        score, pick, u = min(found, key=lambda f: f[1])
        q = np.column_stack([q, u])
        left -= score
        trace.add(len(ids), score, left)
        ids.append(pick)
    scans.columns.unpersist()
    return selection(spark, ids, trace)
