"""Functions for SQL text."""

from __future__ import annotations

import re

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, Row

from ..operators import kernel
from . import random_maps


#: A type, not its name, which only a session could read.
VECTOR = ArrayType(DoubleType())


@F.udtf(returnType="step int, col_id long, score double")
class SelectColumns:
    """select_columns(TABLE(t) PARTITION BY ..., l): greedy choice among the rows (col_id, vec) of a partition."""

    def __init__(self):
        self.ids, self.rows, self.l = [], [], 0

    def eval(self, row: Row, l: int):
        self.ids.append(row["col_id"])
        self.rows.append(row["vec"])
        self.l = l

    def terminate(self):
        if self.rows:
            t = kernel.targeted(np.array(self.rows, dtype=float).T, self.l, ids=np.array(self.ids))
            for i, (p, s) in enumerate(zip(t.picks, t.scores)):
                yield i + 1, int(self.ids[p]), s


@F.udtf(returnType="token string")
class Tokens:
    """tokens(text): a row for each run of a-z of the lower-cased text."""

    def eval(self, text: str):
        for token in re.findall("[a-z]+", (text or "").lower()):
            yield (token,)


@F.udtf(returnType="k int, w double")
class OmegaRow:
    """omega_row(seed, id, r): the non-zero entries of a column's row of the sparse random map."""

    def eval(self, seed: int, col_id: int, r: int):
        for k, w in enumerate(random_maps.hashed_block(seed, [col_id], r)[0].tolist(), 1):
            if w:
                yield k, w


@F.pandas_udf(VECTOR)
def vec_sum(column: pd.Series) -> list:
    """The sum of a group's vectors."""
    return np.sum(np.stack(column.to_list()), axis=0).tolist() if len(column) else []


@F.pandas_udf(VECTOR)
def gram_of(column: pd.Series) -> list:
    """The sum of a group's outer products, m x m by rows."""
    x = np.stack(column.to_list())
    return (x.T @ x).ravel().tolist()


def project_error(q: np.ndarray):
    """A scalar function of a column: its squared distance to the span of an orthonormal basis."""

    @F.pandas_udf("double")
    def error(column: pd.Series) -> pd.Series:
        x = np.stack(column.to_list()) if len(column) else np.zeros((0, len(q)))
        return pd.Series(np.maximum((x * x).sum(axis=1) - ((x @ q) ** 2).sum(axis=1), 0))

    return error


def register(spark: SparkSession) -> None:
    """select_columns, tokens and omega_row, and vec_dot, vec_norm, vec_axpy and vec_hadamard as SQL functions."""
    for name, function in (("select_columns", SelectColumns), ("tokens", Tokens), ("omega_row", OmegaRow)):
        spark.udtf.register(name, function)
    for text in (
        "vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
        "vec_norm(a ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(a, 0D, (s, x) -> s + x * x))",
        "vec_axpy(s DOUBLE, a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(a, b, (x, y) -> s * x + y)",
        "vec_hadamard(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(a, b, (x, y) -> x * y)",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
