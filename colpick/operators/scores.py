"""Greedy selection by recursive scores, with the state of each column beside it.

A row is a column with its two numbers (f, what its residual captures of the
target's residual; g, its residual's energy) and its part in the directions
chosen so far (w).  A step is narrow: the chosen row, which is all that a step
sends out, gives every other row its part in the new direction, and both numbers
follow.  Nothing of n x n entries is formed, and no matrix comes to the driver.

For a given target a row also holds its cross products with it (c).  For the
matrix itself these would be n numbers a column; they are replaced by one sum
over all columns a step, of m numbers.  The state is written to the checkpoint
folder every few steps, so that a lost task goes back so far only.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vec
from . import gram, kernel
from .matrix import ColumnFrame, keys, pack, to_long

LISTS = pa.list_(pa.float64())
STATE = pa.schema([("col_id", pa.int64()), ("vec", LISTS), ("c", LISTS), ("f", pa.float64()), ("g", pa.float64()), ("g0", pa.float64()), ("w", LISTS)])
STATE_DDL = "col_id long, vec array<double>, c array<double>, f double, g double, g0 double, w array<double>"


def cross_products(a: ColumnFrame, b: ColumnFrame) -> DataFrame:
    """(col_id, k, v): b'a by a join on the rows, partial sums before the shuffle; neither side goes to one machine."""
    left, right = to_long(a), to_long(b).select("row_id", F.col("col_id").alias("k"), F.col("value").alias("y"))
    return left.join(right, "row_id").groupBy("col_id", "k").agg(F.sum(F.col("value") * F.col("y")).alias("v"))


def _packed(batch: pa.RecordBatch) -> tuple[np.ndarray, ...]:
    n = batch.num_rows
    lists = [vec.stack(batch.column(i)) for i in (1, 2, 6)]
    return (batch.column(0).to_numpy(), *(x.reshape(n, -1) for x in lists), *(batch.column(i).to_numpy() for i in (3, 4, 5)))


def _row(ids, x, c, f, g, g0, w) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(ids), vec.unstack(x), vec.unstack(c), pa.array(f), pa.array(g), pa.array(g0), vec.unstack(w)], schema=STATE)


def _map(state: DataFrame, change) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield _row(*change(*_packed(batch)))

    return state.mapInArrow(run, STATE_DDL)


def _best(state: DataFrame, chosen: list[int], digits: int, forced: int | None):
    """The row of the best live score, ties to the smaller id; each task sends one row at most."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top = None
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, x, c, w, f, g, g0 = _packed(batch)
            alive = (g > kernel.DEAD * g0) & (g > 0) & ~np.isin(ids, chosen)
            if forced is not None:
                alive &= ids == forced
            score = np.divide(f, g, out=np.zeros(len(ids)), where=alive)
            if (p := kernel.best(score, alive, ids, digits)) is not None and (top is None or score[p] > top[0] * (1 + 10.0**-digits) or (score[p] >= top[0] * (1 - 10.0**-digits) and ids[p] < top[1])):
                top = score[p], ids[p], _row(ids[p : p + 1], x[p : p + 1], c[p : p + 1], f[p : p + 1], g[p : p + 1], g0[p : p + 1], w[p : p + 1])
        if top is not None:
            yield top[2]

    rows = state.mapInArrow(run, STATE_DDL).collect()
    if not rows:
        return None
    best = max(r.f / r.g for r in rows)
    return min((r for r in rows if r.f / r.g >= best * (1 - 10.0**-digits)), key=lambda r: r.col_id)


def _sums(state: DataFrame, m: int, t: int) -> np.ndarray:
    """Over all columns, of their last part w: w a (m numbers), w times each part (t numbers); one row a task, added up."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(m + t)
        for batch in batches:
            if batch.num_rows:
                _, x, _, w, *_ = _packed(batch)
                total += w[:, -1] @ np.hstack([x, w])
        yield pa.RecordBatch.from_arrays([pa.array([0]), vec.unstack(total[None])], schema=gram.PARTIAL)

    got = gram.vector_sums(state.mapInArrow(run, gram.PARTIAL_DDL), m + t).collect()
    return np.array(got[0].partial) if got else np.zeros(m + t)


def _select(a: ColumnFrame, state: DataFrame, l: int, energy: float, own: bool, start, digits: int, cut: int) -> DataFrame:
    from .greedy import selection

    trace, ids, left, queue, v = kernel.Trace(), [], energy, [int(i) for i in start], np.zeros((0, 0))
    now, kept = state, None
    while len(ids) < l:
        forced = queue.pop(0) if queue else None
        p = _best(now, ids, digits, forced)
        if p is None and forced is None:
            break
        if p is None:
            continue
        t, root = len(ids) + 1, float(np.sqrt(p.g))
        ap, wp, score = np.array(p.vec), np.array(p.w), p.f / p.g

        def spread(i, x, c, w, f, g, g0, ap=ap, wp=wp, root=root):
            part = (x @ ap - w @ wp) / root
            return i, x, c, f, g, g0, np.column_stack([w, part])

        now = _map(now, spread)
        if own:
            now = now.persist(StorageLevel.MEMORY_AND_DISK)
            sums = _sums(now, a.m, t)
            z, past, size = sums[: a.m], sums[a.m : -1], float(sums[-1])

            def settle(i, x, c, w, f, g, g0, z=z, past=past, size=size):
                part = w[:, -1]
                f = f - 2 * part * (x @ z - w[:, :-1] @ past) + size * part**2
                return i, x, c, np.maximum(f, 0), np.maximum(g - part**2, 0), g0, w
        else:
            cp = np.array(p.c)
            new = (cp - (v @ wp if len(ids) else 0)) / root
            past, size = (new @ v if len(ids) else np.zeros(0)), float(new @ new)

            def settle(i, x, c, w, f, g, g0, new=new, past=past, size=size):
                part = w[:, -1]
                f = f - 2 * part * (c @ new - w[:, :-1] @ past) + size * part**2
                return i, x, c, np.maximum(f, 0), np.maximum(g - part**2, 0), g0, w

            v = np.column_stack([v, new]) if len(ids) else new[:, None]
        parts, now = now, _map(now, settle)
        if t % cut == 0 and a.spark.sparkContext.getCheckpointDir():
            now = now.checkpoint(eager=True)
        else:
            now = now.persist(StorageLevel.MEMORY_AND_DISK)
            now.count()
        parts.unpersist()
        if kept is not None:
            kept.unpersist()
        kept = now
        left -= score
        trace.add(t - 1, score, left)
        ids.append(int(p.col_id))
    if kept is not None:
        kept.unpersist()
    return selection(a.spark, ids, trace)


def _state(a: ColumnFrame, f: DataFrame) -> DataFrame:
    """The state before the first step, of (col_id, f, c) and the columns."""
    g = vec.norm_sq(F.col("vec"))
    none = F.array().cast("array<double>")
    rows = a.df.select("col_id", "vec").join(f, "col_id", "left").select("col_id", "vec", F.coalesce("c", none).alias("c"), F.coalesce("f", F.lit(0.0)).alias("f"), g.alias("g"), g.alias("g0"), none.alias("w"))
    return rows.persist(StorageLevel.MEMORY_AND_DISK)


def scores_select(a: ColumnFrame, l: int, start=(), digits: int = 9, cut: int = 8) -> DataFrame:
    """The columns of :func:`greedy.greedy_select`, by the recursion over the state of each column.

    The first numbers f are row sums of squares of the Gram matrix: of few rows
    they are x'(aa')x for a column x, of many a join on the rows gives them
    without its being kept anywhere.
    """
    if a.m <= 8192:
        middle = gram.row_gram(a)

        def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if batch.num_rows:
                    x = vec.stack(batch.column(1))
                    yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.maximum(((x @ middle) * x).sum(axis=1), 0))], names=["col_id", "f"])

        f = a.df.select("col_id", "vec").mapInArrow(first, "col_id long, f double")
    else:
        half = gram.gram_long(a).where("v != 0")
        both = half.select("p", "v").unionByName(half.where("p != q").select(F.col("q").alias("p"), "v"))
        f = both.groupBy(F.col("p").alias("col_id")).agg(F.sum(F.col("v") * F.col("v")).alias("f"))
    f = f.withColumn("c", F.array().cast("array<double>"))
    state = _state(a, f)
    energy = state.agg(F.sum("g")).first()[0] or 0.0
    out = _select(a, state, l, float(energy), True, start, digits, cut)
    state.unpersist()
    return out


def scores_select_for(a: ColumnFrame, b: np.ndarray | ColumnFrame, l: int, start=(), digits: int = 9, cut: int = 8) -> DataFrame:
    """The columns of :func:`greedy.greedy_select_for`; a ColumnFrame b never leaves its rows, of which r a column stay in the state."""
    if isinstance(b, ColumnFrame):
        energy = b.df.agg(F.sum(vec.norm_sq(F.col("vec")))).first()[0] or 0.0
        names = keys(b.df, "col_id", "row_id").withColumnRenamed("key", "k")
        cross = cross_products(a, b).join(names, "k").select("row_id", "col_id", F.col("v").alias("value"))
        f = pack(cross, names.count(), a.df).df.select("col_id", F.col("vec").alias("c"), vec.norm_sq(F.col("vec")).alias("f"))
    else:
        energy = float((b * b).sum())

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            schema = pa.schema([("col_id", pa.int64()), ("c", LISTS), ("f", pa.float64())])
            for batch in batches:
                if batch.num_rows:
                    c = vec.stack(batch.column(1)) @ b
                    yield pa.RecordBatch.from_arrays([batch.column(0), vec.unstack(c), pa.array((c * c).sum(axis=1))], schema=schema)

        f = a.df.select("col_id", "vec").mapInArrow(run, "col_id long, c array<double>, f double")
    state = _state(a, f)
    out = _select(a, state, l, float(energy), False, start, digits, cut)
    state.unpersist()
    return out
