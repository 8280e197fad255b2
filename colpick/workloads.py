"""Matrices on the given tables, and the experiments over them."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import experiments
from .functions import text
from .operators import baselines, distributed, gram, greedy, matrix, measures
from .operators.matrix import ColumnFrame
from .sources.tables import load

RESULT = experiments.RESULT


# Matrices: frames of cells (row_key, col_key, value), or columns at once.


def emb(spark, d, labels: int | None = None) -> ColumnFrame:
    df = load(spark, d, "embeddings", "vec_id", "embedding", "label")
    return matrix.from_dense(df if labels is None else df.where(F.col("label") < labels), "vec_id", "embedding", 64)


def doc_cells(spark, d, least: int = 50, lang: str | None = None) -> DataFrame:
    docs = load(spark, d, "documents", "doc_id", "text", "lang")
    found = text.counts(docs if lang is None else docs.where(F.col("lang") == lang), "doc_id", F.col("text"))
    return text.frequent(found, least)


def page_cells(spark, d, least: int = 20) -> DataFrame:
    return text.frequent(text.counts(load(spark, d, "pages", "page_id", "html"), "page_id", text.visible(F.col("html"))), least)


def conv_cells(spark, d, least: int = 10) -> DataFrame:
    return text.frequent(text.counts(load(spark, d, "conversations", "conv_id", "text"), "conv_id", F.col("text")), least)


def doc_hash(spark, d, buckets: int = 512) -> ColumnFrame:
    """Hashed token counts of every document, kept for many scans.

    Each text is counted by the task that reads it; only those of repeated ids are shuffled.
    """
    docs = load(spark, d, "documents", "doc_id", "text").where("doc_id is not null")
    found = docs.select(F.col("doc_id").cast("long").alias("col_id"), text.tokens(F.col("text")).alias("t")).mapInArrow(text.histograms(buckets), "col_id long, vec array<double>")
    twice = docs.groupBy(F.col("doc_id").alias("col_id")).count().where("count > 1").select("col_id")
    if not twice.isEmpty():
        sums = gram.vector_sums(found.join(twice, "col_id", "left_semi").select(F.col("col_id").alias("row_id"), F.col("vec").alias("partial")), buckets)
        found = found.join(twice, "col_id", "left_anti").unionByName(sums.select(F.col("row_id").alias("col_id"), F.col("partial").alias("vec")))
    return cached(ColumnFrame(found, buckets))


def star(spark, d) -> DataFrame:
    """Line items with their customer and brand."""
    items = load(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_quantity")
    orders, part = load(spark, d, "orders", "o_orderkey", "o_custkey"), load(spark, d, "part", "p_partkey", "p_brand")
    return items.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(part, F.col("l_partkey") == F.col("p_partkey"))


def brand_cells(spark, d) -> DataFrame:
    return matrix.cells(star(spark, d), F.col("o_custkey"), F.col("p_brand"), F.col("l_quantity"))


def month_cells(spark, d, key: str = "l_partkey") -> DataFrame:
    items = load(spark, d, "lineitem", key, "l_shipdate", "l_quantity")
    return matrix.cells(items, F.date_format(F.trunc("l_shipdate", "month"), "yyyy-MM-dd"), F.col(key), F.col("l_quantity"))


def day_cells(spark, d) -> DataFrame:
    events = load(spark, d, "events", "user_id", "ts")
    return matrix.cells(events, F.date_format("ts", "yyyy-MM-dd"), F.col("user_id"), F.lit(1))


def etype_hour_cells(spark, d) -> DataFrame:
    events = load(spark, d, "events", "user_id", "ts", "event_type")
    return matrix.cells(events, F.concat_ws(":", "event_type", F.hour("ts").cast("string")), F.col("user_id"), F.lit(1))


def numeric_cells(spark, d) -> DataFrame:
    """Numbers of the line items by feature: features are the columns."""
    items = load(spark, d, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax").withColumn("item", F.concat_ws(":", "l_orderkey", "l_linenumber"))
    return matrix.cells(items.unpivot(["item"], ["l_quantity", "l_extendedprice", "l_discount", "l_tax"], "feature", "value"), F.col("item"), F.col("feature"), F.col("value"))


def columns(cells: DataFrame, transpose: bool = False) -> ColumnFrame:
    return matrix.from_cells(cells, transpose)[0]


MATRICES = {
    "emb": emb,
    "doc_tf": lambda s, d: columns(doc_cells(s, d)),
    "doc_en": lambda s, d: columns(doc_cells(s, d, 50, "en")),
    "page_tf": lambda s, d: columns(page_cells(s, d)),
    "conv_tf": lambda s, d: columns(conv_cells(s, d)),
    "doc_hash": doc_hash,
    "term_doc": lambda s, d: columns(doc_cells(s, d), True),
    "brand_cust": lambda s, d: columns(brand_cells(s, d)),
    "cust_brand": lambda s, d: columns(brand_cells(s, d), True),
    "part_month": lambda s, d: columns(month_cells(s, d)),
    "supp_month": lambda s, d: columns(month_cells(s, d, "l_suppkey")),
    "user_day": lambda s, d: columns(day_cells(s, d)),
    "user_etype_hour": lambda s, d: columns(etype_hour_cells(s, d)),
    "emb_classes": lambda s, d: emb(s, d, 4),
}

#: Methods: (matrix, l, seed) to a selection.
CENTRAL = {
    "uniform": lambda a, l, s: baselines.uniform_select(a, l, s),
    "pivoted_qr": lambda a, l, s: baselines.pivoted_qr_select(a, l),
    "strong_rrqr": lambda a, l, s: baselines.strong_rrqr_select(a, l),
    "svd_target": lambda a, l, s: baselines.svd_target_select(a, l, seed=s),
    "two_phase": lambda a, l, s: baselines.two_phase_select(a, l, seed=s),
    "greedy": lambda a, l, s: greedy.greedy_select(a, l),
    "sketch_target": lambda a, l, s: baselines.sketch_target_select(a, l, seed=s),
}
DISTRIBUTED = {
    "uniform": lambda a, l, s: baselines.uniform_select(a, l, s),
    "two_phase_uniform": lambda a, l, s: baselines.two_phase_select(a, l, "uniform", "greedy", s),
    "two_phase_colnorm": lambda a, l, s: baselines.two_phase_select(a, l, "colnorm", "greedy", s),
    "two_phase_leverage": lambda a, l, s: baselines.two_phase_select(a, l, "leverage", "greedy", s),
    "svd_target": lambda a, l, s: baselines.distributed_svd_target_select(a, l, min(100, a.m), s, blocks="hash", n_blocks=4),
    "two_stage_gaussian": lambda a, l, s: distributed.two_stage_select(a, l, 100, "gaussian", seed=s, blocks="hash", n_blocks=4),
    "two_stage_sparse": lambda a, l, s: distributed.two_stage_select(a, l, 100, "sparse_sign", seed=s, blocks="hash", n_blocks=4),
}


def cached(a: ColumnFrame) -> ColumnFrame:
    """The matrix kept for many methods."""
    from pyspark import StorageLevel

    return ColumnFrame(a.df.persist(StorageLevel.MEMORY_AND_DISK), a.m)


def compare(spark: SparkSession, workload: str, name: str, a: ColumnFrame, methods: dict, ls, seeds=range(10)) -> DataFrame:
    """Every method for every l and seed: accuracy against uniform and the best rank, and seconds."""
    a = cached(a)
    n, rows = a.df.count(), []
    for l in ls:
        found, took = {}, {}
        for method, run in methods.items():
            for seed in seeds if method not in experiments.FIXED and "local" not in method else list(seeds)[:1]:
                t = time.time()
                found[f"{method}|{seed}"] = measures.ids_of(run(a, l, seed))
                took[f"{method}|{seed}"] = time.time() - t
        for r in measures.relative_accuracy(a, found, l, 10, 1000).collect():
            method, seed = r.method.split("|")
            rows.append((workload, name, n, a.m, method, l, int(seed), r.rel_acc, r.err, took[r.method]))
    a.df.unpersist()
    return spark.createDataFrame(rows, RESULT)


def central(workload: str, name: str):
    """One of the six central experiments, of all methods."""

    def run(spark, sf_dir, ls=None, seeds=range(10)):
        return experiments.central(workload, name, MATRICES[name](spark, sf_dir), list(experiments.CENTRAL), ls, seeds)

    return run


def spread(workload: str, name: str, leave: tuple = (), ls=(10, 100, 500)):
    methods = [k for k in DISTRIBUTED if k not in leave]

    def run(spark, sf_dir, ls=ls, seeds=range(10)):
        return experiments.spread(workload, name, MATRICES[name](spark, sf_dir), methods, ls, seeds)

    return run


def w_laws(spark, sf_dir, ls=(10, 100, 500), seeds=range(10)):
    """Gaussian against sparse signs."""
    return experiments.spread("laws", "doc_hash", doc_hash(spark, sf_dir), ["two_stage_gaussian", "two_stage_sparse"], ls, seeds)


def w_targets(spark, sf_dir, ls=(5, 10, 20), seeds=range(10)):
    """Singular vectors against a sketch as the target, on matrices of full and of low rank."""
    parts = [experiments.spread("targets", k, MATRICES[k](spark, sf_dir), ["svd_target", "two_stage_sparse"], ls, seeds) for k in ("emb", "part_month", "cust_brand")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def summary(workload):
    """Mean and deviation over the ten seeds, and the place of each method for its l."""

    def run(spark, sf_dir):
        return measures.rank_methods(measures.repeat_stats(workload(spark, sf_dir)), "avg_acc")

    return run


def w_split(spark, sf_dir, l=10, blocks=(4, 8), seeds=range(10)):
    """All columns of a kind on one block: the union of local choices against the common target."""
    from .functions import vec

    a = MATRICES["part_month"](spark, sf_dir)
    # ids in order of energy, so that ranges of ids are ranges of energy
    place = matrix.keys(a.df.select(F.struct(vec.norm_sq(F.col("vec")).alias("e"), "col_id").alias("k")), "k", "place")
    order = a.df.withColumnRenamed("col_id", "was").join(place.select("place", F.col("key.col_id").alias("was")), "was").select(F.col("place").alias("col_id"), "vec")
    a = ColumnFrame(order, a.m)
    out = None
    for c in blocks:
        methods = {
            f"local_union_{c}": lambda a, l, s, c=c: distributed.local_union_select(a, l, c, "range"),
            f"local_union_refined_{c}": lambda a, l, s, c=c: distributed.local_union_select(a, l, c, "range", True, "oversample"),
            f"two_stage_{c}": lambda a, l, s, c=c: distributed.two_stage_select(a, l, 50, seed=s, blocks="range", n_blocks=c),
        }
        rows = compare(spark, "split", "part_month", a, methods, (l,), seeds)
        out = rows if out is None else out.unionByName(rows)
    return out


WORKLOADS = {
    "w1_news": central("w1", "doc_tf"),
    "w2_reviews": central("w2", "doc_en"),
    "w3_pages": central("w3", "page_tf"),
    "w3_conversations": central("w3", "conv_tf"),
    "w4_low_rank": central("w4", "cust_brand"),
    "w5_classes": central("w5", "emb_classes"),
    "w6_all_classes": central("w6", "emb"),
    "w7_big_sparse": spread("w7", "doc_hash"),
    "w8_big_low_rank": spread("w8", "part_month", ("two_stage_gaussian",), (10, 30, 60)),
    "w11_central_summary": summary(central("w11", "emb")),
    "w12_spread_summary": summary(spread("w12", "part_month", ("two_stage_gaussian",), (10, 30, 60))),
    "w13_laws": w_laws,
    "w14_targets": w_targets,
    "w15_split": w_split,
}
