"""Column sketches: the matrix times a random map that is never stored."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import random_maps
from . import gram
from .matrix import ColumnFrame, to_long


def sketch_columns(a: ColumnFrame, r: int, law="sparse_sign", s: int | str = 3, seed: int = 0, combine: str = "in_task", scale: str = "none", draws: str = "mixed") -> DataFrame:
    """(row_id, sketch) of r numbers a row, in one scan.

    combine: 'in_task' adds up within each task before anything is sent;
    'partial_agg' leaves that to the engine's partial aggregation; 'none' sends
    every column's own products, for comparison.  The last two draw from hashes
    that SQL can repeat and take the named laws only; the first does so with
    draws='hash'.  s may be 'sqrt', of the number of columns.
    """
    if s == "sqrt":
        s = random_maps.sparsity(law, s, a.df.count())
    if combine == "in_task":
        out = gram.accumulate(a, lambda ids, _: random_maps.block(seed, ids, r, law, s, draws), r).select("row_id", F.col("partial").alias("sketch"))
    else:
        out = _packed(sketch_long(to_long(a), r, law, s, seed, combine), r)
    if scale == "1/sqrt(r)":
        out = out.withColumn("sketch", F.transform("sketch", lambda x: x / float(r) ** 0.5))
    return out


def sketch_long(long: DataFrame, r: int, law: str = "sparse_sign", s: int = 3, seed: int = 0, combine: str = "partial_agg") -> DataFrame:
    """(row_id, k, v) of the non-zero sums, k from 1 to r; zero draws go before the sum."""
    drawn = long.select("col_id").distinct().withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(r)))).withColumn("w", random_maps.omega(seed, F.col("col_id"), F.col("k"), law, s)).where("w != 0")
    products = long.join(drawn, "col_id").select("row_id", "k", (F.col("value") * F.col("w")).alias("x"))
    if combine == "none":
        products = products.repartition("row_id", "k")
    return products.groupBy("row_id", "k").agg(F.sum("x").alias("v"))


def _packed(sums: DataFrame, r: int) -> DataFrame:
    entries = sums.groupBy("row_id").agg(F.map_from_entries(F.collect_list(F.struct("k", "v"))).alias("e"))
    return entries.select("row_id", F.transform(F.sequence(F.lit(1), F.lit(r)), lambda k: F.coalesce(F.try_element_at("e", k), F.lit(0.0))).alias("sketch"))


def merge(*sketches: DataFrame) -> DataFrame:
    """The sketch of the columns of all, for equal seeds: sketches add up."""
    out = sketches[0]
    for x in sketches[1:]:
        out = out.unionByName(x)
    sums = out.select("row_id", F.posexplode("sketch").alias("k", "v")).groupBy("row_id", "k").agg(F.sum("v").alias("v"))
    return sums.groupBy("row_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "v"))), lambda p: p["v"]).alias("sketch"))


def publish(sketch: DataFrame, m: int, r: int):
    """The sketch on the driver, m x r, after a check of its size."""
    return gram.to_driver(sketch.select("row_id", "sketch"), m, r)
