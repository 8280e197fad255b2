"""Experiment grids: every method for every l and seed, run side by side over the cluster.

The central comparison takes matrices that fit one task.  The matrix is sent out
once, after a check of its size, and the cells of the grid (method, l, seed) are
the rows that are dealt over the tasks; each runs one method and measures what
its columns leave.

The comparison over blocks runs the passes for all seeds together: one pass
sketches for every seed, one pass chooses in each block for every seed's target,
and the last choices, one for each method, l and seed, are cells of a grid again.
Since a greedy choice of fewer columns begins the choice of more, a block chooses
once for the largest l.
"""

from __future__ import annotations

import math
import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .functions import random_maps, vec
from .operators import baselines, distributed, gram, greedy, kernel
from .operators.matrix import ColumnFrame

RESULT = "workload string, matrix string, n long, m int, method string, l int, seed int, rel_acc double, err double, seconds double"
CELL = pa.schema([("method", pa.string()), ("l", pa.int32()), ("seed", pa.int32()), ("err", pa.float64()), ("seconds", pa.float64())])
CELL_DDL = "method string, l int, seed int, err double, seconds double"
#: Seeds of the random subsets that accuracy is measured against.
REFERENCE = range(1000, 1010)
FIXED = ("greedy", "pivoted_qr", "strong_rrqr")


def sweep(n: int, rank: int, step: int = 2, most: int = 25) -> list[int]:
    """l from 1 % to ``most`` % of n, below the rank."""
    return sorted({max(1, min(rank - 1, n * p // 100)) for p in range(1, most + 1, step)})


# Methods on a matrix in one task: (x m x n, ids, l, seed) to positions


def leading(x: np.ndarray, k: int, seed: int, oversample: int = 10) -> tuple[np.ndarray, np.ndarray]:
    """(u, s) of the k leading directions, at random with one power step."""
    k = min(k, *x.shape)
    q = np.linalg.qr(x @ random_maps.block(seed, np.arange(x.shape[1]), min(x.shape[0], k + oversample), "gaussian"))[0]
    q = np.linalg.qr(x @ (x.T @ q))[0]
    u, s, _ = np.linalg.svd(q.T @ x, full_matrices=False)
    return (q @ u)[:, :k], s[:k]


def uniform(x, ids, l, seed):
    keys = [random_maps.hashed_number("u", seed, int(i)) for i in ids]
    return np.lexsort((ids, keys))[:l].tolist()


def weighted(p: np.ndarray, ids, s: int, seed: int) -> list[int]:
    """s positions without replacement, likelier for larger p, by exponential keys."""
    u = (np.array([random_maps.hashed_number("w", seed, int(i)) for i in ids]) + 0.5) / 2.0**32
    live = np.flatnonzero(p > 0)
    return live[np.lexsort((ids[live], -np.log(u[live]) / p[live]))[:s]].tolist()


def phase_one(l: int) -> int:
    return max(l, math.ceil(l * math.log(max(l, 2))))


def two_phase(x, ids, l, seed):
    u, s = leading(x, l, seed)
    v = (u / np.where(s > 0, s, 1)).T @ x
    sample = sorted(weighted((v * v).sum(axis=0), ids, phase_one(l), seed))
    return [sample[p] for p in kernel.pivoted_qr(x[:, sample], l, ids[sample]).picks]


def svd_target(x, ids, l, seed):
    u, s = leading(x, l, seed)
    return kernel.targeted(x, l, u * s, ids).picks


CENTRAL = {
    "uniform": uniform,
    "pivoted_qr": lambda x, ids, l, seed: kernel.pivoted_qr(x, l, ids).picks,
    "strong_rrqr": lambda x, ids, l, seed: kernel.strong_rrqr(x, l, ids).picks,
    "svd_target": svd_target,
    "two_phase": two_phase,
    "greedy": lambda x, ids, l, seed: kernel.targeted(x, l, ids=ids).picks,
    "sketch_target": lambda x, ids, l, seed: kernel.targeted(x, l, x @ random_maps.block(seed, ids, l), ids).picks,
}


def _grid(a: ColumnFrame, cells: list[tuple], payload, run) -> list:
    """Runs ``run(payload, *cell)`` for every cell, dealt over the tasks; the payload is broadcast."""
    spark = a.spark
    shared = spark.sparkContext.broadcast(payload)

    def kernel_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for method, l, seed in zip(*(c.to_pylist() for c in batch.columns[:3])):
                started = time.time()
                err = run(shared.value, method, l, seed)
                yield pa.RecordBatch.from_arrays([pa.array([method]), pa.array([l], pa.int32()), pa.array([seed], pa.int32()), pa.array([float(err)]), pa.array([time.time() - started])], schema=CELL)

    tasks = max(1, min(len(cells), 4 * spark.sparkContext.defaultParallelism))
    # large cells first, then in turn, so that no task gets all of them
    order = sorted(cells, key=lambda c: -c[1])
    rows = spark.createDataFrame([(*c, i % tasks) for i, c in enumerate(order)], "method string, l int, seed int, task int")
    dealt = rows.repartitionByRange(tasks, "task").select("method", "l", "seed")
    out = dealt.mapInArrow(kernel_of, CELL_DDL).collect()
    shared.unpersist()
    return out


def scored(a: ColumnFrame, workload: str, name: str, n: int, found: list, best: dict[int, float]) -> DataFrame:
    """The rows of a grid with accuracy: 0 for the mean of the reference subsets, 100 for the best of rank l, unsquared."""
    base = {}
    for r in found:
        if r.method == "reference":
            base.setdefault(r.l, []).append(r.err)
    rows = []
    for r in found:
        if r.method != "reference":
            zero, top = float(np.mean(base[r.l])), best[r.l]
            acc = 100 * (zero - r.err) / (zero - top) if zero - top > 1e-12 * max(zero, 1e-300) else None
            rows.append((workload, name, n, a.m, r.method, r.l, r.seed, acc, r.err, r.seconds))
    return a.spark.createDataFrame(rows, RESULT)


def central(workload: str, name: str, a: ColumnFrame, methods, ls=None, seeds=range(10), most: int = 16_000_000) -> DataFrame:
    """The central comparison over a sweep of l (1 to 25 % of the columns in steps of 2, below the rank) and ten seeds."""
    ids, x = greedy.local(a, most)
    values = np.linalg.svd(x, compute_uv=False)
    rank = int((values > 1e-7 * values[0]).sum())
    ls = sweep(len(ids), rank) if ls is None else sorted({min(l, rank) for l in ls})
    cells = [(m, l, s) for m in methods for l in ls for s in (seeds if m not in FIXED else list(seeds)[:1])]
    cells += [("reference", l, s) for l in ls for s in REFERENCE]
    energy = float((x * x).sum())

    def run(payload, method, l, seed):
        ids, x = payload
        picks = (CENTRAL.get(method) or uniform)(x, ids, l, seed)
        return np.sqrt(max(0.0, energy - ((kernel.orth(x[:, picks]).T @ x) ** 2).sum()))

    return scored(a, workload, name, len(ids), _grid(a, cells, (ids, x), run), {l: float(np.sqrt((values[l:] ** 2).sum())) for l in ls})


# The comparison over blocks


def _sketches(a: ColumnFrame, seeds, r: int, law: str) -> dict[int, np.ndarray]:
    """A sketch for every seed from one pass."""
    seeds = list(seeds)
    wide = gram.to_driver(gram.accumulate(a, lambda ids, _: np.hstack([random_maps.block(s, ids, r, law) for s in seeds]), r * len(seeds)), a.m, r * len(seeds))
    return {s: wide[:, i * r : (i + 1) * r] for i, s in enumerate(seeds)}


PICKED = pa.schema([("method", pa.string()), ("seed", pa.int32()), ("step", pa.int32()), ("col_id", pa.int64())])


def _block_choices(a: ColumnFrame, targets: dict[tuple[str, int], np.ndarray], l_b: int, n_blocks: int) -> DataFrame:
    """(method, seed, step, col_id): each block's choice for every target, in one pass over the blocks."""
    shared = a.spark.sparkContext.broadcast(targets)

    def choose(ids: list[np.ndarray], rows: kernel.Rows) -> pa.RecordBatch:
        ids = np.concatenate(ids)
        traces = kernel.targeted_many(rows, l_b, list(shared.value.values()), ids)
        out = [(m, s, i, int(ids[p])) for (m, s), trace in zip(shared.value, traces) for i, p in enumerate(trace.picks, 1)]
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out), PICKED)] if out else [pa.array([], f.type) for f in PICKED], schema=PICKED)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # a block's rows stand together; only its compact pieces are held
        ids, rows, block = [], kernel.Rows(), None
        for batch in batches:
            if not batch.num_rows:
                continue
            b = batch.column(2).to_numpy()
            for cut in np.split(np.arange(len(b)), np.flatnonzero(b[1:] != b[:-1]) + 1):
                if ids and b[cut[0]] != block:
                    yield choose(ids, rows)
                    ids, rows = [], kernel.Rows()
                block, piece = b[cut[0]], batch.slice(int(cut[0]), len(cut))
                ids.append(piece.column(0).to_numpy().copy())
                rows.add(vec.stack(piece.column(1)))
        if ids:
            yield choose(ids, rows)

    return distributed.in_blocks(a, "hash", n_blocks).mapInArrow(run, "method string, seed int, step int, col_id long")


def _samples(a: ColumnFrame, weights: dict[str, DataFrame], seeds, s: int) -> DataFrame:
    """(method, seed, step, col_id): s columns without replacement for every law and seed, by exponential keys."""
    frames = [w.select(F.lit(m).alias("method"), "col_id", "p") for m, w in weights.items()]
    rows = frames[0]
    for f in frames[1:]:
        rows = rows.unionByName(f)
    rows = rows.where("p > 0").withColumn("seed", F.explode(F.array(*[F.lit(int(x)) for x in seeds])))
    u = (random_maps.hashed(F.lit("w"), F.col("seed"), F.col("col_id")).cast("double") + 0.5) / float(1 << 32)
    place = F.row_number().over(Window.partitionBy("method", "seed").orderBy("key", "col_id"))
    return rows.withColumn("key", -F.ln(u) / F.col("p")).withColumn("step", place).where(F.col("step") <= s).select("method", "seed", "step", "col_id")


def _kept(rows: DataFrame) -> DataFrame:
    """The rows, made now and kept where they are."""
    from pyspark import StorageLevel

    rows = rows.persist(StorageLevel.MEMORY_AND_DISK)
    rows.count()
    return rows


def spread(workload: str, name: str, a: ColumnFrame, methods, ls=(10, 100, 500), seeds=range(10), r: int = 100, n_blocks: int = 4, gamma: float = 2.0, most_bytes: int = 512 << 20) -> DataFrame:
    """The comparison of two-pass selection with sampling and with singular vectors, for l below the rank.

    seconds: of a cell's last choice, and an even part of the passes that it
    shares with other seeds and l.
    """
    from pyspark import StorageLevel

    seeds, a = list(seeds), ColumnFrame(a.df.persist(StorageLevel.MEMORY_AND_DISK), a.m)
    n = a.df.count()
    middle = gram.row_gram(a)
    values = np.sqrt(np.maximum(np.linalg.eigvalsh(middle)[::-1], 0))
    rank = int((values > 1e-7 * values[0]).sum())
    ls = sorted({min(l, rank - 1, n) for l in ls})
    top = max(ls)
    targets: dict[tuple[str, int], np.ndarray] = {}
    took: dict[str, float] = dict.fromkeys(methods, 0.0)
    for method, law in (("two_stage_gaussian", "gaussian"), ("two_stage_sparse", "sparse_sign")):
        if method in methods:
            t = time.time()
            targets |= {(method, s): b for s, b in _sketches(a, seeds, r, law).items()}
            took[method] += time.time() - t
    k = min(r, rank)
    if {"svd_target", "two_phase_leverage"} & set(methods):
        t = time.time()
        start = _sketches(a, seeds, min(a.m, k + 10), "gaussian")
        found = {s: _directions(middle, y, k) for s, y in start.items()}
        if "svd_target" in methods:
            targets |= {("svd_target", s): u * v for s, (u, v) in found.items()}
            took["svd_target"] += time.time() - t
    picked, size = [], {"uniform": lambda l: l, "reference": lambda l: l}
    for method in dict.fromkeys(m for m, _ in targets):
        t = time.time()
        mine = {key: b for key, b in targets.items() if key[0] == method}
        size[method] = lambda l: distributed.quota_of(l, n_blocks, "oversample", gamma)
        picked.append(_kept(_block_choices(a, mine, size[method](top), n_blocks)))
        took[method] += time.time() - t
    weights = {}
    for method in methods:
        if method in ("uniform", "two_phase_uniform", "two_phase_colnorm"):
            weights[method] = baselines.probabilities(a, "colnorm" if method.endswith("colnorm") else "uniform", top)
    if "two_phase_leverage" in methods:
        u, v = found[seeds[0]]
        weights["two_phase_leverage"] = _leverage(a, u / np.where(v > 0, v, 1))
    if weights:
        t = time.time()
        picked.append(_kept(_samples(a, weights, seeds, min(n, phase_one(top)))))
        for m in weights:
            took[m] += (time.time() - t) / len(weights)
    picked.append(_samples(a, {"reference": baselines.probabilities(a, "uniform", top)}, REFERENCE, top))
    widest = max(phase_one(top), n_blocks * distributed.quota_of(top, n_blocks, "oversample", gamma))
    if 8 * a.m * min(n, widest) > most_bytes:
        raise ValueError(f"{widest} candidate columns of {a.m} entries exceed {most_bytes} bytes: take a smaller l")
    # the last choices: the candidates of a method and a seed, for all l, meet in one task, and none goes to the driver
    need = picked[0]
    for frame in picked[1:]:
        need = need.unionByName(frame)
    energy = float(np.trace(middle))
    shared = a.spark.sparkContext.broadcast((middle, targets))

    def choose(key: tuple, table: pa.Table) -> pa.Table:
        middle, targets = shared.value
        method, seed = (k.as_py() for k in key)
        order = np.argsort(table.column("col_id").to_numpy())
        ids, step = (table.column(c).to_numpy()[order] for c in ("col_id", "step"))
        x, out = vec.stack(table.column("vec").combine_chunks())[order].T, []
        for l in ls:
            started = time.time()
            own = np.flatnonzero(step <= size.get(method, phase_one)(l))
            if method not in ("uniform", "reference"):
                own = own[kernel.targeted(x[:, own], l, targets.get((method, seed)), ids[own]).picks]
            q = kernel.orth(x[:, own])
            err = np.sqrt(max(0.0, energy - float(np.einsum("ij,ij->", q, middle @ q))))
            out.append((method, l, seed, float(err), time.time() - started))
        return pa.table([pa.array(c, f.type) for c, f in zip(zip(*out), CELL)], schema=CELL)

    groups = len(methods) * len(seeds) + len(REFERENCE)
    meet = a.df.join(F.broadcast(need), "col_id").repartition(min(groups, 4 * a.spark.sparkContext.defaultParallelism), "method", "seed")
    out = meet.groupBy("method", "seed").applyInArrow(choose, CELL_DDL).collect()
    shared.unpersist()
    for frame in picked:
        frame.unpersist()
    a.df.unpersist()
    part = {m: t / (len(ls) * len(seeds)) for m, t in took.items()}
    frame = scored(a, workload, name, n, out, {l: float(np.sqrt((values[l:] ** 2).sum())) for l in ls})
    more = F.coalesce(*[F.when(F.col("method") == m, F.lit(t)) for m, t in part.items()], F.lit(0.0))
    return frame.withColumn("seconds", F.col("seconds") + more)


def _directions(middle: np.ndarray, y: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(u, s): k leading directions of a from aa' and a sketch of a, with one power step."""
    q = np.linalg.qr(middle @ np.linalg.qr(y)[0])[0]
    values, vectors = np.linalg.eigh(q.T @ middle @ q)
    order = np.argsort(-values)[:k]
    return q @ vectors[:, order], np.sqrt(np.maximum(values[order], 0))


def _leverage(a: ColumnFrame, left: np.ndarray) -> DataFrame:
    """(col_id, p): squared norms of the rows of the right vectors."""
    schema = pa.schema([("col_id", pa.int64()), ("p", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(((vec.stack(batch.column(1)) @ left) ** 2).sum(axis=1))], schema=schema)

    return a.df.select("col_id", "vec").mapInArrow(run, "col_id long, p double")
