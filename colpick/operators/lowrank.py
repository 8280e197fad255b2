"""What a selection is used for: coordinates, approximations and singular vectors from few columns."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..functions import vec
from . import gram, greedy, kernel
from .matrix import ColumnFrame

ROW = pa.schema([("col_id", pa.int64()), ("vec", pa.list_(pa.float64()))])


def _mapped(a: ColumnFrame, left: np.ndarray) -> ColumnFrame:
    """left * a, column by column."""

    def run(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), vec.unstack(vec.stack(b.column(1)) @ left.T)], schema=ROW)

    return ColumnFrame(a.df.select("col_id", "vec").mapInArrow(run, "col_id long, vec array<double>"), left.shape[0])


def basis(a: ColumnFrame, ids, how: str = "svd") -> np.ndarray:
    return kernel.orth(greedy.by_id(a, ids), how)


def embed(a: ColumnFrame, ids) -> ColumnFrame:
    """Every column's coordinates in the span of the chosen ones."""
    return _mapped(a, basis(a, ids, "qr").T)


def coefficients(a: ColumnFrame, ids, ridge: float = 0.0) -> ColumnFrame:
    """Least-squares weights of the chosen columns for every column; from the Gram matrix if there are few columns of many rows."""
    if gram.is_tall(a):
        every, g = gram.gram_local(a)
        s = np.searchsorted(every, [int(i) for i in ids])
        inner = g[np.ix_(s, s)]
        t = (np.linalg.pinv(inner, hermitian=True) if not ridge else np.linalg.inv(inner + ridge * np.eye(len(s)))) @ g[s]
        return ColumnFrame(a.spark.createDataFrame([(int(i), w.tolist()) for i, w in zip(every, t.T)], "col_id long, vec array<double>"), len(s))
    c = greedy.by_id(a, ids)
    left = np.linalg.pinv(c) if not ridge else np.linalg.solve(c.T @ c + ridge * np.eye(c.shape[1]), c.T)
    return _mapped(a, left)


def project(a: ColumnFrame, ids) -> ColumnFrame:
    """The approximation of every column in the span of the chosen ones."""
    q = basis(a, ids)
    return _mapped(a, q @ q.T)


approximate = project


def approximate_rank_k(a: ColumnFrame, ids, k: int) -> ColumnFrame:
    """The best approximation of rank k within the span of the chosen columns."""
    q = basis(a, ids)
    values, vectors = np.linalg.eigh(gram.row_gram(_mapped(a, q.T)))
    u = q @ vectors[:, np.argsort(-values)[:k]]
    return _mapped(a, u @ u.T)


def approx_svd_from_columns(a: ColumnFrame, ids, k: int) -> tuple[np.ndarray, np.ndarray, DataFrame]:
    """(left vectors m x k, values, frame of right vectors) of that approximation."""
    from .svd import Svd

    q = basis(a, ids)
    values, vectors = np.linalg.eigh(gram.row_gram(_mapped(a, q.T)))
    order = np.argsort(-values)[:k]
    out = Svd(q @ vectors[:, order], np.sqrt(np.maximum(values[order], 0)), a)
    return out.u, out.values, out.v()
