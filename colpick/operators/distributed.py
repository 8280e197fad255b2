"""Selection in two passes over any number of blocks."""

from __future__ import annotations

import math
import warnings
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import random_maps, vec
from . import gram, greedy, kernel
from .matrix import ColumnFrame

CHOSEN = pa.schema([("block", pa.int64()), ("step", pa.int32()), ("col_id", pa.int64()), ("score", pa.float64()), ("left", pa.float64()), ("vec", pa.list_(pa.float64()))])
CHOSEN_DDL = "block long, step int, col_id long, score double, left double, vec array<double>"


def quota_of(l: int, blocks: int, quota: str = "oversample", gamma: float = 2.0) -> int:
    """Columns that each block may send on.

    'floor' can send fewer than l in all, or none with more blocks than l: it
    warns.  'ceil' and 'oversample' send at least one; 'full' all l.  For
    'proportional' see :func:`proportional`.
    """
    if quota == "floor":
        out = l // blocks
        if out * blocks < l:
            warnings.warn(f"floor quota: {out} from each of {blocks} blocks can't make {l}", stacklevel=2)
        return out
    return {"ceil": max(1, math.ceil(l / blocks)), "oversample": max(1, math.ceil(gamma * l / blocks)), "full": l}[quota]


def _kernel(l: int | dict[int, int], target, block_bytes: int):
    """Chooses l columns of each block: a task's columns, cut where they exceed ``block_bytes``.

    l may differ by block.  target: an m x r matrix, or None for the block itself.
    """

    def choose(ids, x, block):
        trace = kernel.targeted(x, l.get(block, 0) if isinstance(l, dict) else l, target, ids)
        p = trace.picks
        return pa.RecordBatch.from_arrays([pa.array([block] * len(p), type=pa.int64()), pa.array(np.arange(1, len(p) + 1, dtype=np.int32)), pa.array(ids[p]), pa.array(trace.scores, type=pa.float64()), pa.array(trace.left, type=pa.float64()), vec.unstack(x[:, p].T) if p else pa.array([], type=pa.list_(pa.float64()))], schema=CHOSEN)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # the block grows in one buffer, whose pages are taken as they are written
        ids, x, n, block = [], None, 0, None
        for batch in batches:
            if not batch.num_rows:
                continue
            b = batch.column(2).to_numpy()
            for cut in np.split(np.arange(len(b)), np.flatnonzero(b[1:] != b[:-1]) + 1):
                if n and (b[cut[0]] != block or x[:n].nbytes > block_bytes):
                    yield choose(np.concatenate(ids), x[:n].T, block)
                    ids, n = [], 0
                piece = batch.slice(int(cut[0]), len(cut))
                block = int(b[cut[0]])
                ids.append(piece.column(0).to_numpy())
                part = vec.stack(piece.column(1))
                if x is None or n + len(part) > len(x):
                    more = np.empty((max(2 * n, min(block_bytes, 256 << 20) // max(8, part[:1].nbytes)) + len(part), part.shape[1]))
                    if n:
                        more[:n] = x[:n]
                    x = more
                x[n : n + len(part)] = part
                n += len(part)
        if n:
            yield choose(np.concatenate(ids), x[:n].T, block)

    return run


def in_blocks(a: ColumnFrame, blocks: str = "partition", n_blocks: int | None = None, order: str = "col_id") -> DataFrame:
    """(col_id, vec, block): the input's own partitions, a hash of the id, or ranges of ``order``.

    Rows of a block stand together; only 'hash' and 'range' shuffle.
    """
    if blocks == "partition":
        return a.df.select("col_id", "vec", F.spark_partition_id().cast("long").alias("block"))
    n = n_blocks or a.spark.sparkContext.defaultParallelism
    if blocks == "hash":
        out = a.df.select("col_id", "vec", F.pmod(F.conv(F.substring(F.md5(F.col("col_id").cast("string").cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(n)).alias("block"))
        return out.repartition(n, "block").sortWithinPartitions("block", "col_id")
    if blocks == "range":
        return a.df.repartitionByRange(n, order).select("col_id", "vec", F.spark_partition_id().cast("long").alias("block"))
    raise ValueError(f"unknown blocks {blocks!r}")


def proportional(rows: DataFrame, l: int, gamma: float = 2.0) -> dict[int, int]:
    """Columns that each block may send on, gamma * l in all by the blocks' sizes, one at least; a count by block."""
    sizes = {r.block: r["count"] for r in rows.groupBy("block").count().collect()}
    return {b: max(1, math.ceil(gamma * l * n / sum(sizes.values()))) for b, n in sizes.items()}


def choose_in_blocks(a: ColumnFrame, l_b: int | dict[int, int], target, blocks: str, n_blocks: int | None, block_bytes: int = 256 << 20) -> DataFrame:
    if not l_b:
        return a.spark.createDataFrame([], CHOSEN_DDL)
    return in_blocks(a, blocks, n_blocks).mapInArrow(_kernel(l_b, target, block_bytes), CHOSEN_DDL)


def sketch_and_blocks(a: ColumnFrame, r: int, law, s: int, seed: int, draws: str) -> tuple[np.ndarray, int]:
    """(sketch, number of tasks that had columns), both from one pass: a last row of the sums counts the tasks."""
    m = a.m

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((m + 1, r))
        for batch in batches:
            if batch.num_rows:
                ids, x = batch.column(0).to_numpy(), vec.stack(batch.column(1))
                total[:m] += x.T @ random_maps.block(seed, ids, r, law, s, draws)
                total[m, 0] = 1
        if total[m, 0]:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(m + 1)), vec.unstack(total)], schema=gram.PARTIAL)

    sums = gram.vector_sums(a.df.select("col_id", "vec").mapInArrow(run, gram.PARTIAL_DDL), r)
    out = gram.to_driver(sums, m + 1, r)
    return out[:m], max(1, int(out[m, 0]))


def merged(candidates: DataFrame, l: int, target, m: int, fanin: int = 64, n_groups: int = 1, block_bytes: int = 256 << 20) -> DataFrame:
    """l columns from candidates, in levels of ``fanin`` groups down to a single task."""
    now = candidates
    while n_groups > fanin:
        n_groups = math.ceil(n_groups / fanin)
        grouped = now.select("col_id", "vec", F.pmod(F.col("block"), F.lit(n_groups)).alias("block")).repartition(n_groups, "block").sortWithinPartitions("block", "col_id")
        now = grouped.mapInArrow(_kernel(l, target, block_bytes), CHOSEN_DDL)
    last = now.select("col_id", "vec", F.lit(0).cast("long").alias("block")).coalesce(1).sortWithinPartitions("col_id")
    return last.mapInArrow(_kernel(l, target, 1 << 62), CHOSEN_DDL).select("step", "col_id", "score", F.col("score").alias("gain"), F.col("left").alias("residual_sq"))


def two_stage_select(a: ColumnFrame, l: int, r: int = 100, law="sparse_sign", s: int = 3, seed: int = 0, n_blocks: int | None = None, quota: str = "oversample", gamma: float = 2.0, blocks: str = "partition", target: np.ndarray | None = None, fanin: int = 64, draws: str = "mixed") -> DataFrame:
    """l columns in two passes: a sketch of all columns, then a choice in each block for the sketch, then one among the chosen.

    residual_sq is of the target: the sketch, or ``target``, m x r, if given.
    The blocks of 'partition' are counted within the first pass; with a target
    of one's own, and for the quota 'proportional', ids alone are read once more.
    """
    from ..plans import planner

    planner.check_budget(a.m, r, l, n_blocks or 1, gamma)
    count = n_blocks
    if target is None:
        target, tasks = sketch_and_blocks(a, r, law, s, seed, draws)
        count = count or (tasks if blocks == "partition" else None)
    if count is None:
        count = max(1, a.df.select(F.spark_partition_id().alias("p")).distinct().count()) if blocks == "partition" else a.spark.sparkContext.defaultParallelism
    l_b = proportional(in_blocks(a, blocks, count).select("block"), l, gamma) if quota == "proportional" else quota_of(l, count, quota, gamma)
    candidates = choose_in_blocks(a, l_b, target, blocks, count)
    return merged(candidates, l, target, a.m, fanin, count)


def local_union_select(a: ColumnFrame, l: int, n_blocks: int | None = None, blocks: str = "hash", refine: bool = False, quota: str = "ceil") -> DataFrame:
    """Each block chooses for its own columns; the union comes back, or l of it chosen for the union."""
    count = n_blocks or a.spark.sparkContext.defaultParallelism
    union = choose_in_blocks(a, quota_of(l, count, quota), None, blocks, count)
    if refine:
        return merged(union, l, None, a.m)
    # block by block, one step of each at a time, up to l
    rows = union.select("block", "step", "col_id", "score").orderBy("step", F.desc("score"), "col_id").limit(l).collect()
    trace = kernel.Trace()
    for i, row in enumerate(rows):
        trace.add(i, row.score, float("nan"))
    return greedy.selection(a.spark, [row.col_id for row in rows], trace)
