"""Leading singular values and vectors."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from ..functions import vec
from . import gram
from .matrix import ColumnFrame
from .sketch import publish, sketch_columns


@dataclass
class Svd:
    """Left vectors m x k and values on the driver; right vectors by column when asked for."""

    u: np.ndarray
    values: np.ndarray
    a: ColumnFrame

    def v(self) -> DataFrame:
        """(col_id, v): the rows of the right vectors, in one narrow pass."""
        import pyarrow as pa

        u, s = self.u, self.values
        schema = pa.schema([("col_id", pa.int64()), ("v", pa.list_(pa.float64()))])

        def run(batches):
            for b in batches:
                if b.num_rows:
                    yield pa.RecordBatch.from_arrays([b.column(0), vec.unstack(vec.stack(b.column(1)) @ u / np.where(s > 0, s, 1))], schema=schema)

        return self.a.df.select("col_id", "vec").mapInArrow(run, "col_id long, v array<double>")


def _inner(a: ColumnFrame, q: np.ndarray) -> np.ndarray:
    """q'aa'q, in one scan."""
    return q.T @ gram.to_driver(gram.accumulate(a, lambda _, x: x @ q, q.shape[1]), a.m, q.shape[1])


def randomized_svd(a: ColumnFrame, k: int, oversample: int = 10, power: int = 1, law="gaussian", seed: int = 0) -> Svd:
    """k leading triplets by a random range finder: two scans, and one more for each power step."""
    r = min(a.m, k + oversample)
    q = np.linalg.qr(publish(sketch_columns(a, r, law, seed=seed), a.m, r))[0]
    for _ in range(power):
        q = np.linalg.qr(gram.to_driver(gram.accumulate(a, lambda _, x, q=q: x @ q, q.shape[1]), a.m, q.shape[1]))[0]
    values, vectors = np.linalg.eigh(_inner(a, q))
    order = np.argsort(-values)[:k]
    return Svd(q @ vectors[:, order], np.sqrt(np.maximum(values[order], 0)), a)


def exact_svd(a: ColumnFrame, k: int | None = None) -> Svd:
    """Triplets from aa', in one scan; for up to 8192 rows."""
    values, vectors = np.linalg.eigh(gram.row_gram(a))
    order = np.argsort(-values)[:k]
    return Svd(vectors[:, order], np.sqrt(np.maximum(values[order], 0)), a)


def numerical_rank(a: ColumnFrame, tol: float = 1e-7) -> int:
    s = exact_svd(a).values
    return int((s > tol * max(s[0], 1e-300)).sum()) if len(s) else 0
