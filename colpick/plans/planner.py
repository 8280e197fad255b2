"""Costs of the formulations, the choice between them, and budgets that are checked before a run."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame


@dataclass(frozen=True)
class FormChoice:
    form: str
    reason: str
    flops: float
    driver_bytes: float


def estimate(form: str, m: int, n: int, nnz: float, l: int) -> dict[str, float]:
    """Operations of all l steps, bytes that the form keeps, and scans of the data."""
    return {
        "naive": {"flops": float(l) * m**2 * n**2, "bytes": 8.0 * m * n, "scans": 0},
        "residual": {"flops": float(l) * m * n**2, "bytes": 8.0 * m * n, "scans": 0},
        "gram": {"flops": n * nnz + float(l) * n**2, "bytes": 8.0 * n**2, "scans": 1},
        "scores": {"flops": n**2 * float(m) + l * float(n) * (m + l), "bytes": 8.0 * n * (2 + l), "scans": 0},
        "rowspace": {"flops": nnz * m + float(l) * n * m**2, "bytes": 8.0 * m * (m + l), "scans": 1 + l},
        "two_stage": {"flops": nnz * 100 + float(n) * m * l, "bytes": 8.0 * m * 100, "scans": 2},
    }[form]


def choose(m: int, n: int, nnz: float, l: int, gram_columns: int = 2048, rows: int = 8192, scans: int = 1000) -> FormChoice:
    """The cheapest form whose memory is bounded at these sizes.

    The Gram matrix of n columns takes products of pairs of columns, aa' of pairs
    of rows: the fewer of both decide, if either fits the driver.
    """
    if n <= gram_columns and (n <= m or m > rows):
        form, why = "gram", f"{n} columns: their Gram matrix fits the driver"
    elif m <= rows and l <= scans:
        form, why = "rowspace", f"{m} rows: aa' fits the driver, {l} scans"
    else:
        form, why = "two_stage", f"{m} x {n} and {l} columns: two passes whatever the sizes"
    cost = estimate(form, m, n, nnz, l)
    return FormChoice(form, why, cost["flops"], cost["bytes"])


def check_budget(m: int, r: int, l: int, blocks: int, gamma: float = 2.0, driver_bytes: float = 512e6, task_bytes: float = 1e9) -> dict[str, float]:
    """Volumes of the two-stage selector; raises where one machine would get more than it can hold."""
    out = {"sketch_shuffle": 8.0 * blocks * m * r, "sketch_on_driver": 8.0 * m * r, "broadcast": 8.0 * m * r, "candidates": 8.0 * m * max(l * gamma, blocks)}
    if out["sketch_on_driver"] > driver_bytes:
        raise ValueError(f"a sketch of {m} x {r} exceeds the driver's {driver_bytes:.0f} bytes: hash the rows to fewer")
    if 8.0 * m * max(l, 1) > task_bytes:
        raise ValueError(f"{l} columns of {m} entries exceed a task's {task_bytes:.0f} bytes")
    return out


def count_scans(df: DataFrame) -> int:
    """File scans of the executed plan, reused exchanges counted once."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return sum("FileScan" in line for line in text.splitlines())
