"""Joins, samples and reports around selections."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def unused(name: str, *frames: DataFrame) -> str:
    """``name``, made longer until no column of the frames has it."""
    known = {c.lower() for f in frames for c in f.columns}
    while name.lower() in known:
        name += "_"
    return name


def topk(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group."""
    r = unused("_r", df)
    return df.withColumn(r, F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col(r) <= k).drop(r)


def chosen(df: DataFrame, selection: DataFrame, key: str = "col_id") -> DataFrame:
    """Rows of selected keys; the selection has few rows."""
    return df.join(F.broadcast(selection.select(F.col("col_id").alias(key))), key, "left_semi")


def unchosen(df: DataFrame, selection: DataFrame, key: str = "col_id") -> DataFrame:
    return df.join(F.broadcast(selection.select(F.col("col_id").alias(key))), key, "left_anti")


def zero_fill(ids: DataFrame, cells: DataFrame, key: str, value: str) -> DataFrame:
    """Every id with the sum of its values, 0 without any."""
    sums = cells.groupBy(key).agg(F.sum(value).alias(value))
    return ids.join(sums, key, "left").withColumn(value, F.coalesce(value, F.lit(0.0)))


def asof_join(left: DataFrame, right: DataFrame, by: str, ts: str, value: str) -> DataFrame:
    """Each left row with the latest right ``value`` of its key at or before its time: one shuffle, no join."""
    v, side = unused("_v", left, right), unused("_left", left, right)
    both = left.withColumn(v, F.lit(None).cast(right.schema[value].dataType)).withColumn(side, F.lit(1))
    other = right.select(by, ts, F.col(value).alias(v), F.lit(0).alias(side))
    seen = Window.partitionBy(by).orderBy(ts, side).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.unionByName(other, allowMissingColumns=True).withColumn(value, F.last(v, ignorenulls=True).over(seen)).where(F.col(side) == 1).drop(v, side)


def range_join(left: DataFrame, right: DataFrame, key: str, at: str, ts: str, width: int) -> DataFrame:
    """Pairs with left.at <= right.ts < left.at + width, in integer units, by buckets of that width."""
    b = unused("_b", left, right)
    l = left.withColumn(b, F.explode(F.array(F.floor(F.col(at) / width), F.floor(F.col(at) / width) + 1)))
    r = right.withColumn(b, F.floor(F.col(ts) / width))
    return l.join(r, [key, b]).where((F.col(ts) >= F.col(at)) & (F.col(ts) < F.col(at) + width)).drop(b)


def wide(df: DataFrame, row: str, column: str, value: str, names: list) -> DataFrame:
    """A report table with one column a name."""
    return df.groupBy(row).pivot(column, names).agg(F.first(value))


def pairs(df: DataFrame, key: str, condition: Column | None = None, other: str = "other") -> DataFrame:
    """Pairs of rows with key < the other's key that meet a condition: a nested loop, for tables of a few thousand rows.

    The other row's columns have the suffix ``other``.
    """
    right = df.select([F.col(c).alias(f"{c}_{other}") for c in df.columns])
    ordered = F.col(key) < F.col(f"{key}_{other}")
    return df.join(F.broadcast(right), ordered if condition is None else ordered & condition)


def top_terms(counts: DataFrame, k: int) -> DataFrame:
    """The k most frequent tokens of each text in cells (col_key, row_key, value), ties by the token."""
    return topk(counts, ["col_key"], [F.desc("value"), F.col("row_key")], k)


def page(df: DataFrame, order: list[Column], offset: int, limit: int) -> DataFrame:
    """Rows offset + 1 to offset + limit of a total order."""
    return df.orderBy(*order).offset(offset).limit(limit)


def compared(first: DataFrame, second: DataFrame) -> DataFrame:
    """(col_id, first, second): the steps at which two selections have a column, null where one lacks it."""
    return first.select("col_id", F.col("step").alias("first")).join(second.select("col_id", F.col("step").alias("second")), "col_id", "full_outer")
