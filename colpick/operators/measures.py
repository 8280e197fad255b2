"""Accuracy and cost of a selection."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vec
from . import baselines, gram, greedy, kernel, svd
from .matrix import ColumnFrame


def ids_of(s) -> list[int]:
    return [r.col_id for r in s.orderBy("step").collect()] if isinstance(s, DataFrame) else [int(i) for i in s]


def residuals(a: ColumnFrame, bases: list[np.ndarray]) -> tuple[float, list[float]]:
    """(energy of a, squared residual for each basis), all in one scan."""

    def run(batches):
        out = np.zeros(1 + len(bases))
        for b in batches:
            if b.num_rows:
                x = vec.stack(b.column(0)).T
                e = (x * x).sum(axis=0)
                out[0] += e.sum()
                for i, q in enumerate(bases):
                    out[1 + i] += np.maximum(e - ((q.T @ x) ** 2).sum(axis=0), 0).sum()
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(out))), pa.array(out)], names=["i", "v"])

    got = {r.i: r.v for r in a.df.select("vec").mapInArrow(run, "i long, v double").groupBy("i").agg(F.sum("v").alias("v")).collect()}
    return got.get(0, 0.0), [got.get(i + 1, 0.0) for i in range(len(bases))]


def bases(a: ColumnFrame, selections: list[list[int]]) -> list[np.ndarray]:
    """Orthonormal bases of many selections; their columns are fetched in one job."""
    every = sorted({i for s in selections for i in s})
    at, x = {i: k for k, i in enumerate(every)}, greedy.by_id(a, every)
    return [kernel.orth(x[:, [at[i] for i in s]]) for s in selections]


def residual_sq(a: ColumnFrame, s) -> float:
    """Squared Frobenius distance of a to the span of the selection."""
    return residuals_of(a, [ids_of(s)])[1][0]


def residuals_of(a: ColumnFrame, selections: list[list[int]]) -> tuple[float, list[float]]:
    """(energy of a, squared residual for each selection); from the Gram matrix if there are few columns of many rows."""
    if not gram.is_tall(a):
        return residuals(a, bases(a, selections))
    ids, g = gram.gram_local(a)
    energy = float(np.trace(g))
    return energy, [max(0.0, energy - gram.explained(g, np.searchsorted(ids, s))) for s in selections]


def residual_norm(a: ColumnFrame, s, kind: str = "fro", rounds: int = 30) -> float:
    """The distance in the Frobenius norm, or in the spectral one by power iteration."""
    if kind == "fro":
        return residual_sq(a, s) ** 0.5
    q = kernel.orth(greedy.by_id(a, ids_of(s)))
    from .gram import row_gram

    inner = row_gram(a)
    p = np.eye(a.m) - q @ q.T
    inner = p @ inner @ p
    x = np.ones(a.m)
    for _ in range(rounds):
        x = inner @ x
        n = np.linalg.norm(x)
        if n == 0:
            return 0.0
        x /= n
    return float(np.sqrt(max(0.0, x @ inner @ x)))


def best_rank_error(a: ColumnFrame, l: int, rows: int = 8192) -> float:
    """The least distance of any matrix of rank l.

    Of more than ``rows`` rows, an upper bound from a randomized decomposition
    with three power steps: what its l leading directions leave.
    """
    if a.m <= rows:
        s = svd.exact_svd(a).values
        return float(np.sqrt((s[l:] ** 2).sum()))
    found = svd.randomized_svd(a, l, power=3)
    energy = a.df.agg(F.sum(vec.norm_sq(F.col("vec")))).first()[0] or 0.0
    return float(np.sqrt(max(0.0, energy - (found.values**2).sum())))


def sketch_records(a: ColumnFrame, r: int, law: str = "sparse_sign", s: int = 3, seed: int = 0, tasks: int = 4) -> DataFrame:
    """(combine, records): rows that a sketch sends over the network.

    'none': every column's own products, n m r for a dense matrix and law;
    'in_task': the rows of one partial sum for each of ``tasks`` tasks.
    """
    from ..functions import random_maps
    from .matrix import to_long

    w = random_maps.omega(seed, F.col("col_id"), F.col("k"), law, s)
    every = to_long(a).withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(r)))).where(w != 0)
    return every.agg(F.count("*").alias("records")).select(F.lit("none").alias("combine"), "records").unionByName(a.spark.createDataFrame([("in_task", tasks * a.m)], "combine string, records long"))


def relative_accuracy(a: ColumnFrame, selections: dict[str, object], l: int, repeats: int = 10, seed: int = 0) -> DataFrame:
    """(method, l, rel_acc, err, err_uniform, err_best): 0 for a random subset, 100 for the best of rank l.

    The random error is the mean over ``repeats`` subsets; all residuals come
    from one scan.  rel_acc is null where both ends agree.
    """
    named = {k: ids_of(v) for k, v in selections.items()}
    uniform = [ids_of(baselines.uniform_select(a, l, seed + i)) for i in range(repeats)]
    _, left = residuals(a, bases(a, [*named.values(), *uniform]))
    err = [float(np.sqrt(x)) for x in left]
    base, low = float(np.mean(err[len(named) :])), best_rank_error(a, l)
    rows = [(k, l, 100 * (base - e) / (base - low) if base - low > 1e-12 * max(base, 1e-300) else None, e, base, low) for k, e in zip(named, err)]
    return a.spark.createDataFrame(rows, "method string, l int, rel_acc double, err double, err_uniform double, err_best double")


def repeat(a: ColumnFrame, methods: dict[str, Callable[[int], object]], l: int, seeds=range(10)) -> DataFrame:
    """(method, l, avg_acc, std_acc, avg_seconds) over the seeds; sample standard deviation.

    All selections meet the same ten random subsets, and are measured in one scan.
    """
    took, found = {}, {}
    for seed in seeds:
        for k, f in methods.items():
            t = time.time()
            found[f"{k}|{seed}"] = ids_of(f(seed))
            took[f"{k}|{seed}"] = time.time() - t
    rows = [(r.method.rpartition("|")[0], l, r.rel_acc, took[r.method]) for r in relative_accuracy(a, found, l, 10, 1000).collect()]
    return repeat_stats(a.spark.createDataFrame(rows, "method string, l int, rel_acc double, seconds double"))


def growth(selection: DataFrame) -> DataFrame:
    """(l, share): the part of the target's energy that the first l columns of a selection explain, from its own gains."""
    first = selection.where("step = 1").select((F.col("gain") + F.col("residual_sq")).alias("energy"))
    return selection.join(F.broadcast(first)).select(F.col("step").alias("l"), (1 - F.col("residual_sq") / F.col("energy")).alias("share"))


def repeat_stats(results: DataFrame) -> DataFrame:
    return results.groupBy("method", "l").agg(F.avg("rel_acc").alias("avg_acc"), F.stddev_samp("rel_acc").alias("std_acc"), F.avg("seconds").alias("avg_seconds"))


def rank_methods(results: DataFrame, by: str = "rel_acc") -> DataFrame:
    """``results`` with the place of each method for its l: 1 is best."""
    return results.withColumn("place", F.dense_rank().over(Window.partitionBy("l").orderBy(F.desc(by))))


def distance_distortion(a: ColumnFrame, b: np.ndarray, pairs: list[tuple[int, int]], scale: float = 1.0) -> DataFrame:
    """(i, j, ratio) of squared row distances in a sketch and in the matrix."""
    from .gram import row_gram

    g = row_gram(a)
    rows = [(i, j, float(scale * ((b[i] - b[j]) ** 2).sum() / d)) for i, j in pairs if (d := g[i, i] + g[j, j] - 2 * g[i, j]) > 0]
    return a.spark.createDataFrame(rows, "i int, j int, ratio double")


def sketch_error_ratio(a: ColumnFrame, s, b: np.ndarray, scale: float = 1.0) -> float:
    """Residual of the (scaled) sketch over that of the matrix, for one selection."""
    q = kernel.orth(greedy.by_id(a, ids_of(s)))
    return scale * kernel.residual_sq(b, q) / residuals(a, [q])[1][0]


def overlap(s1: DataFrame, s2: DataFrame) -> int:
    return s1.select("col_id").intersect(s2.select("col_id")).count()


def coverage_by(s: DataFrame, groups: DataFrame, key: str) -> DataFrame:
    """(key, n, chosen): members of each group of (col_id, key), and those selected."""
    marked = groups.join(s.select("col_id", F.lit(1).alias("hit")), "col_id", "left")
    return marked.groupBy(key).agg(F.count("*").alias("n"), F.count("hit").alias("chosen"))


def optimum_ratio(a: ColumnFrame, s, l: int) -> float:
    """What a selection explains over what the best subset explains."""
    energy, left = residuals_of(a, [ids_of(s), ids_of(baselines.exhaustive_select(a, l))])
    return (energy - left[0]) / (energy - left[1])
