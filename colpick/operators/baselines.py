"""The selectors that the greedy ones are compared with."""

from __future__ import annotations

import itertools
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import random_maps, vec
from . import distributed, gram, greedy, kernel, svd
from .gram import explained, gram_local
from .matrix import ColumnFrame
from .sketch import publish, sketch_columns


def _listed(a: ColumnFrame, ids, scores=None) -> DataFrame:
    trace = kernel.Trace()
    for i, s in enumerate(scores if scores is not None else [float("nan")] * len(ids)):
        trace.add(i, s, float("nan"))
    return greedy.selection(a.spark, ids, trace)


def uniform_ids(df: DataFrame, l: int, seed: int = 0) -> DataFrame:
    """(col_id, h): l columns without replacement, those of least hash; a top-l, no sort of all."""
    return df.select("col_id", random_maps.hashed(F.lit("u"), F.lit(seed), F.col("col_id")).alias("h")).orderBy("h", "col_id").limit(l)


def uniform_select(a: ColumnFrame, l: int, seed: int = 0) -> DataFrame:
    return _listed(a, [r.col_id for r in uniform_ids(a.df, l, seed).collect()])


def weighted_ids(weights: DataFrame, s: int, seed: int = 0) -> DataFrame:
    """(col_id, key): s of (col_id, p) without replacement, likelier for larger p > 0, by exponential keys."""
    u = (random_maps.hashed(F.lit("w"), F.lit(seed), F.col("col_id")).cast("double") + 0.5) / float(1 << 32)
    return weights.where("p > 0").select("col_id", (-F.ln(u) / F.col("p")).alias("key")).orderBy("key", "col_id").limit(s)


def probabilities(a: ColumnFrame, prob: str, l: int, seed: int = 0, k: int | None = None) -> DataFrame:
    """(col_id, p) up to a factor: 'uniform', 'colnorm' or 'leverage' of the k leading right vectors."""
    if prob == "uniform":
        return a.df.select("col_id", F.lit(1.0).alias("p"))
    if prob == "colnorm":
        return a.df.select("col_id", vec.norm_sq(F.col("vec")).alias("p"))
    if prob == "leverage":
        return svd.randomized_svd(a, k or min(l, 100, a.m), seed=seed).v().select("col_id", vec.norm_sq(F.col("v")).alias("p"))
    raise ValueError(f"unknown probabilities {prob!r}")


def pivoted_qr_select(a: ColumnFrame, l: int) -> DataFrame:
    """Pivots by largest residual norm, one scan a step; from the Gram matrix if there are few columns of many rows."""
    if gram.is_tall(a):
        ids, g = gram.gram_local(a)
        return greedy.selection(a.spark, ids, kernel.on_gram(g, l, ids, by_norm=True))
    return greedy._by_scans(a, l, None, float("nan"))


def strong_rrqr_select(a: ColumnFrame, l: int, factor: float = 2.0, max_swaps: int = 200, most: int = 5_000_000) -> DataFrame:
    """Pivoted QR, then swaps that enlarge the chosen volume by more than ``factor``; on the driver up to ``most`` entries, beyond by scans."""
    if a.names().limit(most // max(1, a.m) + 1).count() * a.m <= most:
        ids, x = greedy.local(a, most)
        return greedy.selection(a.spark, ids, kernel.strong_rrqr(x, l, ids, factor, max_swaps))
    return _rrqr_by_scans(a, l, factor, max_swaps)


def _rrqr_by_scans(a: ColumnFrame, l: int, factor: float, max_swaps: int) -> DataFrame:
    """The same with the chosen columns alone on the driver: each task sends the column whose best swap enlarges the volume most."""
    ids = [r.col_id for r in greedy._by_scans(a, l, None, float("nan")).orderBy("step").collect()]
    c, frame = greedy.by_id(a, ids), a.df.select("col_id", "vec")
    for _ in range(max_swaps if ids else 0):
        q, r = np.linalg.qr(c)
        if np.abs(np.diag(r)).min() < 1e-12 * max(1e-300, np.abs(np.diag(r)).max()):
            break
        inverse = np.linalg.inv(r)

        def growth(x, q=q, inverse=inverse):
            inside = q.T @ x
            outside = np.maximum((x * x).sum(axis=0) - (inside**2).sum(axis=0), 0)
            return np.sqrt((inverse @ inside) ** 2 + np.outer((inverse**2).sum(axis=1), outside))

        def scored(i, x, batch, growth=growth, chosen=tuple(ids)):
            return growth(x).max(axis=0), ~np.isin(i, chosen)

        top = greedy._best_of(frame, scored, 9)
        if top is None or top.score <= factor:
            break
        x = np.array(top.vec)
        i = int(np.argmax(growth(x[:, None])[:, 0]))
        ids[i], c[:, i] = int(top.col_id), x
    q, r = np.linalg.qr(c)

    def shares(batches):
        total = np.zeros(1 + q.shape[1])
        for b in batches:
            if b.num_rows:
                x = vec.stack(b.column(1))
                total += np.concatenate([[(x * x).sum()], ((x @ q) ** 2).sum(axis=0)])
        yield pa.RecordBatch.from_arrays([pa.array([0]), vec.unstack(total[None])], schema=gram.PARTIAL)

    energy, *taken = gram.to_driver(gram.vector_sums(frame.mapInArrow(shares, gram.PARTIAL_DDL), 1 + len(ids)), 1, 1 + len(ids))[0]
    trace = kernel.Trace()
    for k, own in enumerate(np.diag(r) ** 2):
        trace.add(k, own, energy - sum(taken[: k + 1]))
    return greedy.selection(a.spark, ids, trace)


def svd_target(a: ColumnFrame, k: int, scaled: bool = True, exact: bool = False, seed: int = 0) -> np.ndarray:
    found = svd.exact_svd(a, k) if exact else svd.randomized_svd(a, min(k, a.m), seed=seed)
    return found.u * found.values if scaled else found.u


def svd_target_select(a: ColumnFrame, l: int, k: int | None = None, scaled: bool = True, exact: bool = False, seed: int = 0) -> DataFrame:
    """Greedy for the leading singular directions."""
    return greedy.greedy_select_for(a, svd_target(a, k or l, scaled, exact, seed), l)


def distributed_svd_target_select(a: ColumnFrame, l: int, k: int = 100, seed: int = 0, **options) -> DataFrame:
    """The two-stage selector for U S of rank k in place of a sketch."""
    return distributed.two_stage_select(a, l, target=svd_target(a, k, True, seed=seed), **options)


def sketch_target_select(a: ColumnFrame, l: int, r: int | None = None, law="sparse_sign", seed: int = 0) -> DataFrame:
    """Greedy for a sketch, of l directions by default."""
    r = r or l
    return greedy.greedy_select_for(a, publish(sketch_columns(a, r, law, seed=seed), a.m, r), l)


def two_phase_select(a: ColumnFrame, l: int, prob: str = "leverage", cut: str = "pivoted_qr", seed: int = 0, log_base: float = math.e, k: int | None = None, cut_on: str = "columns") -> DataFrame:
    """A random sample of l log l columns, cut down to l by 'pivoted_qr', 'strong_rrqr' or 'greedy'.

    cut_on: the sampled columns themselves, or their rows of the right vectors.
    """
    s = max(l, math.ceil(l * math.log(max(l, 2), log_base)))
    if prob == "uniform":
        sample = [r.col_id for r in uniform_ids(a.df, s, seed).collect()]
    else:
        sample = [r.col_id for r in weighted_ids(probabilities(a, prob, l, seed, k), s, seed).collect()]
    sample.sort()
    if cut_on == "right_vectors":
        right = {r.col_id: r.v for r in svd.randomized_svd(a, k or min(l, 100, a.m), seed=seed).v().where(F.col("col_id").isin(sample)).collect()}
        x = np.array([right[i] for i in sample]).T
    else:
        x = greedy.by_id(a, sample)
    ids = np.array(sample, dtype=np.int64)
    trace = {"pivoted_qr": kernel.pivoted_qr, "strong_rrqr": kernel.strong_rrqr, "greedy": lambda x, l, ids: kernel.targeted(x, l, ids=ids)}[cut](x, l, ids)
    return greedy.selection(a.spark, ids, trace)


def exhaustive_select(a: ColumnFrame, l: int, most: int = 30) -> DataFrame:
    """The best l columns of all subsets, for up to ``most`` columns, in order of ids; each step has what it adds to those before."""
    ids, g = gram_local(a, most)
    top, best = -1.0, ()
    for s in itertools.combinations(range(len(ids)), min(l, len(ids))):
        gain = explained(g, s)
        if gain > top * (1 + 1e-12):
            top, best = gain, s
    trace, energy, before = kernel.Trace(), float(np.trace(g)), 0.0
    for k, i in enumerate(best):
        now = explained(g, best[: k + 1])
        trace.add(i, now - before, energy - now)
        before = now
    return greedy.selection(a.spark, ids, trace)


local_union_select = distributed.local_union_select


def kmeans_nearest_select(a: ColumnFrame, l: int, seed: int = 0, rounds: int = 10) -> DataFrame:
    """The columns nearest to the centres of k-means."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    data = a.df.select("col_id", "vec", array_to_vector("vec").alias("features"))
    centres = KMeans(k=l, seed=seed, maxIter=rounds).fit(data).clusterCenters()
    far = [F.struct(vec.norm_sq(F.zip_with("vec", F.array(*[F.lit(float(x)) for x in c]), lambda x, y: x - y)).alias("d"), F.col("col_id")) for c in centres]
    best = a.df.agg(*[F.min(x).alias(f"c{i}") for i, x in enumerate(far)]).first()
    return _listed(a, sorted({best[i].col_id for i in range(len(centres))}))


def kmedoids_select(a: ColumnFrame, l: int, seed: int = 0, rounds: int = 10, trial: int = 64) -> DataFrame:
    """Medoids of all columns by alternating assignment and update, each over the whole matrix.

    A round reads all columns twice.  The first assigns them and sums up each
    cluster; the ``trial`` columns nearest to its mean, which the squared
    distance sum favours, are its candidates.  The second gives the sum of
    distances from all the cluster's columns to each candidate, and the least
    wins if it is better than the present medoid.  Tasks send sums and candidates.
    """
    medoids = by_ids_or_none(a, [r.col_id for r in uniform_ids(a.df, l, seed).collect()])
    for _ in range(rounds):
        centres, means = medoids[1], None
        for stage in ("means", "candidates"):
            got = a.df.select("col_id", "vec").mapInArrow(_cluster(stage, centres, means, trial), "j int, col_id long, n double, vec array<double>").collect()
            if stage == "means":
                means = [sum((np.array(r.vec) for r in got if r.j == j), np.zeros(a.m)) / max(1.0, sum(r.n for r in got if r.j == j)) for j in range(len(centres))]
        best: list[list] = []
        for j in range(len(centres)):
            near = sorted(((r.n, r.col_id, r.vec) for r in got if r.j == j), key=lambda x: x[:2])[:trial]
            best.append([(int(medoids[0][j]), centres[j]), *((c, np.array(v)) for _, c, v in near if c != medoids[0][j])])
        sums: dict[tuple[int, int], float] = {}
        for r in a.df.select("col_id", "vec").mapInArrow(_costs(centres, best), "j int, col_id long, n double, vec array<double>").collect():
            sums[r.j, r.col_id] = sums.get((r.j, r.col_id), 0.0) + r.n
        new = [min(cand, key=lambda c, j=j: (round(sums.get((j, c[0]), 0.0), 9), c[0])) for j, cand in enumerate(best)]
        if [c for c, _ in new] == list(medoids[0]):
            break
        medoids = np.array([c for c, _ in new]), np.array([v for _, v in new])
    return _listed(a, sorted(set(int(i) for i in medoids[0])))


def by_ids_or_none(a: ColumnFrame, ids: list[int]) -> tuple[np.ndarray, np.ndarray]:
    return np.array(ids, dtype=np.int64), greedy.by_id(a, ids).T


CLUSTER = pa.schema([("j", pa.int32()), ("col_id", pa.int64()), ("n", pa.float64()), ("vec", pa.list_(pa.float64()))])


def _distance(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum((x * x).sum(1)[:, None] + (y * y).sum(1)[None] - 2 * x @ y.T, 0))


def _cluster(stage: str, centres: np.ndarray, means, trial: int):
    """Kernel: by cluster, the sum of its columns; or those of a task that are nearest to its mean."""

    def run(batches):
        sums, counts, held = np.zeros_like(centres), np.zeros(len(centres)), [[] for _ in centres]
        for batch in batches:
            if batch.num_rows:
                ids, x = batch.column(0).to_numpy(), vec.stack(batch.column(1))
                near = _distance(x, centres).argmin(axis=1)
                for j in range(len(centres)):
                    own = near == j
                    if stage == "means":
                        sums[j] += x[own].sum(axis=0)
                        counts[j] += own.sum()
                    elif own.any():
                        far = _distance(x[own], means[j][None])[:, 0]
                        held[j] = sorted([*held[j], *zip(far.tolist(), ids[own].tolist(), x[own])], key=lambda t: t[:2])[:trial]
        rows = [(j, -1, counts[j], sums[j]) for j in range(len(centres)) if counts[j]] if stage == "means" else [(j, i, d, v) for j, h in enumerate(held) for d, i, v in h]
        if rows:
            j, i, n, v = zip(*rows)
            yield pa.RecordBatch.from_arrays([pa.array(j, pa.int32()), pa.array(i, pa.int64()), pa.array(n, pa.float64()), vec.unstack(np.array(v))], schema=CLUSTER)

    return run


def _costs(centres: np.ndarray, candidates: list[list]):
    """Kernel: by cluster, the sum of distances from a task's columns of it to each candidate."""

    def run(batches):
        sums = [np.zeros(len(c)) for c in candidates]
        for batch in batches:
            if batch.num_rows:
                x = vec.stack(batch.column(1))
                near = _distance(x, centres).argmin(axis=1)
                for j, c in enumerate(candidates):
                    sums[j] += _distance(x[near == j], np.array([v for _, v in c])).sum(axis=0)
        rows = [(j, i, s) for j, c in enumerate(candidates) for (i, _), s in zip(c, sums[j].tolist())]
        j, i, n = zip(*rows)
        yield pa.RecordBatch.from_arrays([pa.array(j, pa.int32()), pa.array(i, pa.int64()), pa.array(n, pa.float64()), pa.nulls(len(j), CLUSTER.field("vec").type)], schema=CLUSTER)

    return run


def lsa_embed(a: ColumnFrame, k: int, seed: int = 0) -> DataFrame:
    """(col_id, v): coordinates on the leading singular directions, the less readable alternative to columns."""
    return svd.randomized_svd(a, k, seed=seed).v()
