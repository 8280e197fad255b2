"""Exact top-k by inner product with a pivot table.

Vectors are integers.  Every block of vectors carries its precomputed table of
distances to many pivots, in reduced form: the distances from x to the pivots
and to the origin fix the place of x within the pivots' span, as coordinates on
an orthonormal basis of it, and its distance to the span.  Two vectors differ
at least by the distance of their places and the difference of their distances
to the span, which is the greatest lower bound that the table can give (at most
one pivot at a time would give the largest |d(q, p) - d(x, p)|, which is never
more).  With the norms, it bounds the score from above.

A query takes the candidates of a block in the order of that bound, the best
first in steps, and stops as soon as the next bound is below its k-th score so
far: all that are left are eliminated without an evaluation.

Blocks of queries meet blocks of candidates; each side is cut into blocks of a
bounded number of rows, and each task reads pairs of blocks one after another,
keeping the k best of every query it has seen.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import batch_of, durable

BLOCK_DDL = "ids binary, vectors binary, n int, width int"
BLOCK = pa.schema([("ids", pa.binary()), ("vectors", pa.binary()), ("n", pa.int32()), ("width", pa.int32())])
FOUND = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])
FOUND_DDL = "query_id long, vec_id long, score long"


def quantise(vector: Column, scale: int = 64) -> Column:
    """floor(scale * x) of each component as a double; null if the vector is null or has a null or non-finite component."""
    wide = F.transform(vector, lambda x: F.floor(x.cast("double") * scale))
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) == float("inf")))
    return F.when(vector.isNotNull() & ~F.coalesce(bad, F.lit(True)), wide)


def blocks(vectors: DataFrame, rows: int) -> DataFrame:
    """(ids, vectors, n, width): the rows (id, vec) packed, ``rows`` a block at most and one width each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, tuple[list, list]] = {}

        def pack(width):
            ids, vecs = held.pop(width)
            return batch_of(BLOCK, [np.array(ids, dtype=np.int64).tobytes()], [np.array(vecs, dtype=np.int64).tobytes()], [len(ids)], [width])

        for batch in batches:
            for key, vec in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ids, vecs = held.setdefault(len(vec), ([], []))
                ids.append(key)
                vecs.append(vec)
                if len(ids) >= rows:
                    yield pack(len(vec))
        for width in list(held):
            yield pack(width)

    return vectors.select("id", "vec").mapInArrow(run, BLOCK_DDL)


def _exact(q: np.ndarray, x: np.ndarray) -> type:
    """The fastest type in which inner products of rows of q and x are exact."""
    top = float(np.abs(q).max(initial=0)) * float(np.abs(x).max(initial=0)) * max(1, x.shape[1])
    return np.float32 if top < 1 << 24 else np.float64 if top < 1 << 53 else np.int64


def basis_of(pivots: np.ndarray) -> np.ndarray:
    """Orthonormal basis (dimension x rank) of the pivots' span."""
    if not pivots.size:
        return np.zeros((pivots.shape[1], 0))
    u, values, _ = np.linalg.svd(pivots.T.astype(np.float64), full_matrices=False)
    return u[:, values > 1e-9 * max(float(values[0]), 1e-300)]


def _table(x: np.ndarray, basis: np.ndarray) -> np.ndarray:
    """Coordinates of each row within the pivots' span, and last its distance to the span."""
    a = x.astype(np.float64)
    inside = a @ basis
    return np.hstack([inside, np.sqrt(np.maximum((a * a).sum(1) - (inside * inside).sum(1), 0))[:, None]])


class Best:
    """The k best (score, id) of each query of a block so far, ties to smaller ids."""

    def __init__(self, ids: np.ndarray, k: int):
        self.ids, self.k = ids, k
        self.kept = [(np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64)) for _ in ids]

    def floor(self, i: int) -> float:
        scores, _ = self.kept[i]
        return float(scores[-1]) if len(scores) >= self.k else -np.inf

    def add(self, i: int, scores: np.ndarray, ids: np.ndarray) -> None:
        scores, ids = np.concatenate([self.kept[i][0], scores]), np.concatenate([self.kept[i][1], ids])
        order = np.lexsort((ids, -scores))[: self.k]
        self.kept[i] = scores[order], ids[order]

    def rows(self) -> Iterator[pa.RecordBatch]:
        n = [len(s) for s, _ in self.kept]
        if sum(n):
            yield batch_of(FOUND, np.repeat(self.ids, n), np.concatenate([i for _, i in self.kept]), np.concatenate([s for s, _ in self.kept]))


def search_block(best: Best, q: np.ndarray, q_table: np.ndarray, x: np.ndarray, x_ids: np.ndarray, x_table: np.ndarray, step: int = 64, tile: int = 32) -> int:
    """Adds a block's candidates to ``best``; returns how many were evaluated.

    Each query evaluates its candidates in the order of their bounds, in steps
    that double, and stops before the first bound below its k-th score.  Bounds
    are widened by more than their rounding errors.
    """
    kind = _exact(q, x)
    queries, values = q.astype(kind), x.astype(kind)
    places = np.ascontiguousarray(x_table.T, dtype=np.float32)
    far = float(np.sqrt((x_table * x_table).sum(1).max(initial=0)))
    seen = 0
    for begin in range(0, len(q), tile):
        rows = range(begin, min(begin + tile, len(q)))
        bounds = q_table[rows.start : rows.stop].astype(np.float32) @ places
        for r, i in enumerate(rows):
            slack = 1e-6 * (q_table.shape[1] + 8) * far * float(np.sqrt((q_table[i] * q_table[i]).sum())) + 1e-3
            bound = bounds[r] + np.float32(slack)
            live = np.flatnonzero(bound >= best.floor(i)) if best.floor(i) > -np.inf else np.arange(len(x))
            size = step
            while len(live):
                if len(live) > size:  # the ``size`` best bounds now, the others only if the next of them can still win
                    part = np.argpartition(-bound[live], size)
                    now, live = live[part[:size]], live[part[size:]]
                else:
                    now, live = live, live[:0]
                scores = values[now] @ queries[i]
                seen += len(now)
                good = (scores >= best.floor(i)) & (x_ids[now] != best.ids[i])
                if good.any():
                    best.add(i, scores[good].astype(np.int64), x_ids[now[good]])
                live = live[bound[live] >= best.floor(i)]
                size *= 2
    return seen


def _search(k: int, share: list | None = None):
    """Kernel over pairs of blocks: the k best of every query.

    It keeps k pairs for each query of the blocks it has met.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[bytes, Best] = {}
        for batch in batches:
            for r in range(batch.num_rows):
                row = batch.slice(r, 1).to_pylist()[0]
                width, ids = row["width"], np.frombuffer(row["q_ids"], dtype=np.int64)
                q = np.frombuffer(row["q_vectors"], dtype=np.int64).reshape(len(ids), width)
                best = known.setdefault((row["q"], width), Best(ids, k))
                x_ids = np.frombuffer(row["ids"], dtype=np.int64)
                x = np.frombuffer(row["vectors"], dtype=np.int64).reshape(len(x_ids), width)
                tables = (np.frombuffer(row[c], dtype=np.float64).reshape(n, -1) for c, n in (("q_table", len(ids)), ("table", len(x_ids))))
                seen = search_block(best, q, next(tables), x, x_ids, next(tables))
                if share is not None:
                    share.append((seen, len(q) * len(x)))
        for best in known.values():
            yield from best.rows()

    return run


def _with_table(frame: DataFrame, bases: dict[int, np.ndarray]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([*BLOCK, ("table", pa.binary())])
        for batch in batches:
            tables = [_table(np.frombuffer(v, dtype=np.int64).reshape(-1, w) if w else np.zeros((n, 0)), bases[w]).tobytes() for v, n, w in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist())]
            yield batch_of(schema, *batch.columns, tables)

    return frame.mapInArrow(run, BLOCK_DDL + ", table binary")


def top_k(vectors: DataFrame, k: int = 20, every: int = 20, n_pivots: int = 56, query_rows: int = 512, block_rows: int = 8192, scale: int = 64, id_col: str = "vec_id", vector_col: str = "embedding", max_widths: int = 64) -> DataFrame:
    """(query_id, rank, vec_id, score): the k best other rows of each query by integer inner product.

    Queries are the rows whose id is divisible by ``every``; candidates are all
    rows but the query's own, of the query's dimension.  Ties go to the smaller
    id.  Rows with a null id, and vectors that are null or hold null or
    non-finite components, take no part; rows that share the query's id count
    as its own.  Repeated candidate ids are separate candidates.
    """
    usable = vectors.select(F.col(id_col).cast("long").alias("id"), quantise(F.col(vector_col), scale).alias("vec")).where("id is not null and vec is not null")
    # pivots: the first by hash of each dimension, a bounded number
    per = Window.partitionBy("width").orderBy("h", "id", "vec")
    sample = usable.withColumn("h", F.xxhash64("id")).orderBy("h", "id", "vec").limit(n_pivots * max_widths).withColumn("width", F.size("vec"))
    chosen: dict[int, list] = {}
    for r in sample.withColumn("r", F.row_number().over(per)).where(F.col("r") <= n_pivots).collect():
        chosen.setdefault(r.width, []).append(list(r.vec))

    class Bases(dict):
        def __missing__(self, width):  # a rare dimension that the sample lacks: the origin is its only pivot
            return np.zeros((width, 0))

    pivots = Bases({w: basis_of(np.array(v, dtype=np.int64).reshape(len(v), w)) for w, v in chosen.items()})
    candidates = durable(_with_table(blocks(usable, block_rows), pivots))
    asked = usable.where(F.pmod("id", F.lit(every)) == 0).repartition(F.pmod(F.xxhash64("id"), F.lit(997)))
    queries = _with_table(blocks(asked.coalesce(max(1, asked.sparkSession.sparkContext.defaultParallelism)), query_rows), pivots)
    queries = queries.select(F.col("ids").alias("q_ids"), F.col("vectors").alias("q_vectors"), F.col("table").alias("q_table"), "width")
    queries = durable(queries.withColumn("q", F.monotonically_increasing_id()))
    # a query block meets every candidate block of its width
    groups = max(1, min(4096, queries.count()))
    spread = candidates.withColumn("g", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))))
    pairs = spread.join(queries.withColumn("g", F.pmod(F.xxhash64("q"), F.lit(groups)).cast("int")), ["g", "width"])
    pairs = pairs.select("q", "q_ids", "q_vectors", "q_table", "ids", "vectors", "table", "width")
    found = pairs.mapInArrow(_search(k), FOUND_DDL)
    first = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(first)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
