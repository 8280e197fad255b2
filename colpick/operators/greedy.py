"""Greedy selection over a whole matrix.  All forms choose the same columns."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vec
from ..plans import planner
from . import gram, kernel
from .matrix import ColumnFrame

SELECTION = "step int, col_id long, score double, gain double, residual_sq double"
CANDIDATE = pa.schema([("col_id", pa.int64()), ("score", pa.float64()), ("vec", pa.list_(pa.float64()))])
CANDIDATE_DDL = "col_id long, score double, vec array<double>"


def selection(spark, ids, trace: kernel.Trace) -> DataFrame:
    """(step, col_id, score, gain, residual_sq) in order of choice."""
    rows = [(i + 1, int(ids[p]), s, s, left) for i, (p, s, left) in enumerate(zip(trace.picks, trace.scores, trace.left))]
    return spark.createDataFrame(rows, SELECTION)


def local(a: ColumnFrame, most: int = 5_000_000) -> tuple[np.ndarray, np.ndarray]:
    """(ids, m x n) on the driver, in order of ids, up to ``most`` entries."""
    limit = max(1, most // max(1, a.m))
    rows = a.df.select("col_id", "vec").limit(limit + 1).collect()
    if len(rows) > limit:
        raise ValueError(f"more than {most} entries for a form that runs on the driver")
    rows.sort(key=lambda r: r[0])
    return np.array([r[0] for r in rows], dtype=np.int64), (np.array([r[1] for r in rows], dtype=np.float64).T if rows else np.zeros((a.m, 0)))


def by_id(a: ColumnFrame, ids) -> np.ndarray:
    """m x l matrix of the named columns, in the order of the names."""
    wanted = [int(i) for i in ids]
    got = {r[0]: r[1] for r in a.df.where(F.col("col_id").isin(wanted)).collect()} if wanted else {}
    return np.array([got[i] for i in wanted], dtype=np.float64).reshape(len(wanted), a.m).T


def _best_by_task(q: np.ndarray, middle: np.ndarray | None, chosen: set[int], digits: int):
    """Kernel: the best column of a task, by the state (q, middle) alone."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top = None
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, x = batch.column(0).to_numpy(), vec.stack(batch.column(1)).T
            e = x - q @ (q.T @ x)
            own, g0 = (e * e).sum(axis=0), (x * x).sum(axis=0)
            alive = (own > kernel.DEAD * g0) & (own > 0) & ~np.isin(ids, list(chosen))
            value = own if middle is None else (e * (middle @ e)).sum(axis=0)
            score = np.divide(value, own, out=np.zeros(len(ids)), where=alive) if middle is not None else np.where(alive, own, 0)
            if (p := kernel.best(score, alive, ids, digits)) is not None:
                now = (score[p], ids[p], x[:, p])
                if top is None or now[0] > top[0] * (1 + 10.0**-digits) or (now[0] >= top[0] * (1 - 10.0**-digits) and now[1] < top[1]):
                    top = now
        if top is not None:
            yield pa.RecordBatch.from_arrays([pa.array([int(top[1])]), pa.array([float(top[0])]), pa.array([top[2].tolist()], type=pa.list_(pa.float64()))], schema=CANDIDATE)

    return run


def _by_scans(a: ColumnFrame, l: int, middle: np.ndarray | None, energy: float, start=(), rel_tol: float | None = None, digits: int = 9) -> DataFrame:
    """One narrow job a step: each task scores its columns from the basis so far and sends its best one.

    The state is the basis and ``middle`` (bb' for a target b), both of bounded
    size, so that nothing is kept by column and a lost task is simply run again.
    """
    q, trace, ids, left = np.zeros((a.m, 0)), kernel.Trace(), [], energy
    for i, x in zip(start, by_id(a, start).T):
        e = x - q @ (q.T @ x)
        own = float(e @ e)
        if own > kernel.DEAD * float(x @ x):
            score = float(e @ (e if middle is None else middle @ e)) / (1 if middle is None else own)
            left -= score
            trace.add(len(ids), score, left)
            ids.append(int(i))
            q = kernel.orth(np.column_stack([q, e]), "gs")
    while len(ids) < l and not (rel_tol is not None and left <= rel_tol * energy):
        rows = a.df.select("col_id", "vec").mapInArrow(_best_by_task(q, middle, set(ids), digits), CANDIDATE_DDL)
        found = rows.collect()  # one row a task at most
        if not found:
            break
        top = max(r.score for r in found)
        pick = min((r for r in found if r.score >= top * (1 - 10.0**-digits)), key=lambda r: r.col_id)
        x = np.array(pick.vec)
        for _ in range(2):
            x = x - q @ (q.T @ x)
        q = np.column_stack([q, x / np.linalg.norm(x)])
        left -= pick.score
        trace.add(len(ids), pick.score, left)
        ids.append(pick.col_id)
    return selection(a.spark, ids, trace)


def _best_of(a: DataFrame, scored, digits: int):
    """The best row (col_id, score, vec) of ``a`` by ``scored(ids, x)`` to (score, alive); each task sends one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tops = []
        for batch in batches:
            if batch.num_rows:
                ids, x = batch.column(0).to_numpy(), vec.stack(batch.column(1))
                score, alive = scored(ids, x.T, batch)
                if (p := kernel.best(score, alive, ids, digits)) is not None:
                    tops.append((float(score[p]), int(ids[p]), x[p].tolist()))
        if tops:
            most = max(t[0] for t in tops)
            score, i, x = min((t for t in tops if t[0] >= most * (1 - 10.0**-digits)), key=lambda t: t[1])
            yield pa.RecordBatch.from_arrays([pa.array([i]), pa.array([score]), pa.array([x], type=pa.list_(pa.float64()))], schema=CANDIDATE)

    found = a.mapInArrow(run, CANDIDATE_DDL).collect()
    if not found:
        return None
    top = max(r.score for r in found)
    return min((r for r in found if r.score >= top * (1 - 10.0**-digits)), key=lambda r: r.col_id)


def _by_residual(a: ColumnFrame, l: int, digits: int = 9) -> DataFrame:
    """The residual matrix itself, formed and deflated column by column where the columns are; ee' stands for e'e."""
    now = a.df.select("col_id", "vec", vec.norm_sq(F.col("vec")).alias("g0")).persist(StorageLevel.MEMORY_AND_DISK)
    trace, ids, middle = kernel.Trace(), [], gram.row_gram(ColumnFrame(now, a.m))
    while len(ids) < l:

        def scored(i, e, batch, middle=middle, chosen=tuple(ids)):
            own = (e * e).sum(axis=0)
            alive = (own > kernel.DEAD * batch.column(2).to_numpy()) & (own > 0) & ~np.isin(i, chosen)
            return np.divide((e * (middle @ e)).sum(axis=0), own, out=np.zeros(len(i)), where=alive), alive

        if (top := _best_of(now, scored, digits)) is None:
            break
        u = np.array(top.vec) / np.linalg.norm(top.vec)

        def deflate(batches, u=u):
            for b in batches:
                if b.num_rows:
                    e = vec.stack(b.column(1))
                    yield pa.RecordBatch.from_arrays([b.column(0), vec.unstack(e - np.outer(e @ u, u)), b.column(2)], names=["col_id", "vec", "g0"])

        before, now = now, now.mapInArrow(deflate, "col_id long, vec array<double>, g0 double").persist(StorageLevel.MEMORY_AND_DISK)
        middle = gram.row_gram(ColumnFrame(now, a.m))
        before.unpersist()
        trace.add(len(ids), top.score, float(np.trace(middle)))
        ids.append(int(top.col_id))
    now.unpersist()
    return selection(a.spark, ids, trace)


def _naive(a: ColumnFrame, l: int, digits: int = 9) -> DataFrame:
    """The whole criterion for each candidate, by an orthonormal basis of its own, dealt over the tasks; aa' stands for the target."""
    a = ColumnFrame(a.df.select("col_id", "vec").persist(StorageLevel.MEMORY_AND_DISK), a.m)
    middle = gram.row_gram(a)
    energy = left = float(np.trace(middle))
    trace, ids, chosen = kernel.Trace(), [], np.zeros((a.m, 0))
    while len(ids) < l:

        def scored(i, x, batch, chosen=chosen, left=left, taken=tuple(ids)):
            loss = np.empty(len(i))
            for k in range(len(i)):
                q = kernel.orth(np.column_stack([chosen, x[:, k]]))
                loss[k] = max(0.0, energy - float(np.einsum("ij,ij->", q, middle @ q)))
            gain = left - loss
            return gain, (gain > kernel.DEAD * energy) & ~np.isin(i, taken)

        if (top := _best_of(a.df, scored, digits)) is None:
            break
        left -= top.score
        trace.add(len(ids), top.score, left)
        ids.append(int(top.col_id))
        chosen = np.column_stack([chosen, np.array(top.vec)])
    a.df.unpersist()
    return selection(a.spark, ids, trace)


def greedy_select(a: ColumnFrame, l: int, form: str = "auto", start=(), rel_tol: float | None = None) -> DataFrame:
    """At most l columns, each the one that lowers the squared residual of ``a`` most.

    Fewer rows come back if the rank is reached, or ``rel_tol`` of the energy is
    left.  Columns in the span of the chosen ones, and zero columns, are never
    chosen; ties go to the smaller id.  form: 'gram' for few columns,
    'rowspace' for few rows, 'scores' with a state by column, 'sparse' by
    intervals of scores for many rows and many columns made of cells, which
    'rowspace' becomes beyond 8192 rows; 'residual' and 'naive' on the driver
    beyond 8192 rows, 'local' always.
    """
    if l <= 0:
        return a.spark.createDataFrame([], SELECTION)
    if form == "auto":
        n = a.names().limit(2049).count()  # no shuffle, and no more rows than decide
        form = planner.choose(a.m, n, float(n) * a.m, l).form
        if form == "gram" and start:
            form = "rowspace" if a.m <= 8192 else "scores"
    if form in ("rowspace", "two_stage") and a.m > 8192 and a.sparse is not None and not start and rel_tol is None:
        form = "sparse"  # exact as well
    if form == "sparse":
        from .bounds import sparse_select

        return sparse_select(a.sparse, a.m, l)
    if form == "two_stage":
        from .distributed import two_stage_select

        return two_stage_select(a, l)
    if form == "gram":
        kept = a if a.cells is not None else ColumnFrame(a.df.persist(StorageLevel.MEMORY_AND_DISK), a.m)
        ids, g = gram.gram_local(kept)
        if kept is not a:
            kept.df.unpersist()
        return selection(a.spark, ids, kernel.on_gram(g, l, ids))
    if form == "scores":
        from .scores import scores_select

        return scores_select(a, l, start=start)
    if form == "rowspace":
        middle = gram.row_gram(a)
        return _by_scans(a, l, middle, float(np.trace(middle)), start, rel_tol)
    if form in ("residual", "naive") and a.m <= 8192:
        return _by_residual(a, l) if form == "residual" else _naive(a, l)
    ids, x = local(a)
    at = {int(i): k for k, i in enumerate(ids)}
    trace = {"local": lambda: kernel.targeted(x, l, ids=ids, start=[at[int(i)] for i in start]), "residual": lambda: kernel.on_residual(x, l, ids), "naive": lambda: kernel.naive(x, l, ids)}[form]()
    return selection(a.spark, ids, trace)


def greedy_select_for(a: ColumnFrame, b: np.ndarray | ColumnFrame, l: int, form: str = "rowspace", start=()) -> DataFrame:
    """At most l columns of ``a`` that span the target ``b`` best; b has the rows of a, residual_sq is of b.

    b: an m x r array, or a ColumnFrame of which bb' is formed in one scan.  form:
    'rowspace', 'scores' with a state by column (a ColumnFrame meets a by a join
    on the rows, whatever its size), or 'local' on the driver.
    """
    if form == "scores":
        from .scores import scores_select_for

        return scores_select_for(a, b, l, start)
    if form == "local":
        ids, x = local(a)
        at = {int(i): k for k, i in enumerate(ids)}
        return selection(a.spark, ids, kernel.targeted(x, l, b if isinstance(b, np.ndarray) else local(b)[1], ids, start=[at[int(i)] for i in start]))
    middle = gram.row_gram(b) if isinstance(b, ColumnFrame) else b @ b.T
    return _by_scans(a, l, middle, float(np.trace(middle)), start)


def block_greedy(a: ColumnFrame, l: int, batch: int = 4) -> DataFrame:
    """Takes the ``batch`` best columns of each scan at a time: fewer scans, less careful choice."""
    middle, q, ids = gram.row_gram(a), np.zeros((a.m, 0)), []
    left, trace = float(np.trace(middle)), kernel.Trace()

    def top(q, chosen, k):
        def run(batches):
            for b in batches:
                if b.num_rows:
                    x = vec.stack(b.column(1)).T
                    e = x - q @ (q.T @ x)
                    own = (e * e).sum(axis=0)
                    alive = (own > kernel.DEAD * (x * x).sum(axis=0)) & ~np.isin(b.column(0).to_numpy(), list(chosen))
                    s = np.divide((e * (middle @ e)).sum(axis=0), own, out=np.zeros(len(own)), where=alive)
                    at = [i for i in np.argsort(-s, kind="stable")[:k] if alive[i]]
                    yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at, type=pa.int64())), pa.array(s[at]), vec.unstack(x[:, at].T) if at else pa.array([], type=pa.list_(pa.float64()))], schema=CANDIDATE)

        return run

    while len(ids) < l:
        rows = a.df.select("col_id", "vec").mapInArrow(top(q, set(ids), batch), CANDIDATE_DDL).orderBy(F.desc("score"), "col_id").limit(batch).collect()
        before = len(ids)
        for r in rows[: l - len(ids)]:
            e = np.array(r.vec) - q @ (q.T @ np.array(r.vec))
            own = float(e @ e)
            if own > kernel.DEAD * float(np.dot(r.vec, r.vec)):
                score = float(e @ (middle @ e)) / own
                left -= score
                trace.add(len(ids), score, left)
                ids.append(r.col_id)
                q = kernel.orth(np.column_stack([q, e]), "gs")
        if len(ids) == before:
            break
    return selection(a.spark, ids, trace)


GROUPED = pa.schema([("grp", pa.int64()), ("step", pa.int32()), ("col_id", pa.int64()), ("score", pa.float64())])


def select_per_group(rows: DataFrame, l: int) -> DataFrame:
    """(grp, step, col_id, score): l columns of each group of (grp, col_id, vec), each group for itself.

    A group is held by one task: this is for many small problems.
    """

    def run(table: pa.Table) -> pa.Table:
        ids, x = table.column("col_id").to_numpy(), vec.stack(table.column("vec").combine_chunks()).T
        t = kernel.targeted(x, l, ids=ids)
        n = len(t.picks)
        return pa.table([pa.array([table.column("grp")[0].as_py()] * n, pa.int64()), pa.array(np.arange(1, n + 1, dtype=np.int32)), pa.array(ids[t.picks], pa.int64()), pa.array(t.scores, pa.float64())], schema=GROUPED)

    return rows.select("grp", "col_id", "vec").groupBy("grp").applyInArrow(run, "grp long, step int, col_id long, score double")


def select_cogrouped(columns: DataFrame, cross: DataFrame, r: int, l: int) -> DataFrame:
    """(grp, step, col_id, score): l columns of each group for a common target of r columns.

    columns: (grp, col_id, vec); cross: (grp, col_id, k, v), their products with
    the target, k from 0.  The target itself goes nowhere.
    """

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return GROUPED.empty_table()
        ids, x = left.column("col_id").to_numpy(), vec.stack(left.column("vec").combine_chunks()).T
        order = np.argsort(ids)
        c = np.zeros((r, len(ids)))
        at = order[np.searchsorted(ids[order], right.column("col_id").to_numpy())] if right.num_rows else np.empty(0, dtype=int)
        c[right.column("k").to_numpy(), at] = right.column("v").to_numpy()
        t = kernel.targeted(x, l, ids=ids, cross=c)
        n = len(t.picks)
        return pa.table([pa.array([left.column("grp")[0].as_py()] * n, pa.int64()), pa.array(np.arange(1, n + 1, dtype=np.int32)), pa.array(ids[t.picks], pa.int64()), pa.array(t.scores, pa.float64())], schema=GROUPED)

    # new names for the keys, which may come from one frame on both sides
    fresh = lambda df, *more: df.select(F.col("grp").cast("long").alias("grp"), F.col("col_id").cast("long").alias("col_id"), *more).groupBy("grp")
    left, right = fresh(columns, "vec"), fresh(cross, "k", "v")
    return left.cogroup(right).applyInArrow(run, "grp long, step int, col_id long, score double")
