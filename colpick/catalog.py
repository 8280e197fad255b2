"""Registered queries of the selection library and their SQL twins."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import oracle, twins, workloads
from .functions import random_maps, text, udfs, vec
from .operators import baselines, distributed, gram, greedy, lowrank, matrix, measures, relational, sketch, svd
from .sources.tables import load
from .streaming import streams

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


def flagship(spark, sf_dir) -> DataFrame:
    """The ten most representative embeddings, with their labels."""
    a = workloads.emb(spark, sf_dir)
    labels = load(spark, sf_dir, "embeddings", "vec_id", "label").withColumnRenamed("vec_id", "col_id")
    return labels.join(F.broadcast(greedy.greedy_select(a, 10, "rowspace")), "col_id").select("step", "col_id", "label", "score", "residual_sq")


# Cells of the matrices


def _cells(f, row, col, value):
    return lambda s, d: f(s, d).select(F.col("row_key").alias(row), F.col("col_key").alias(col), F.col("value").alias(value))


for _name, _f, _sql in (
    ("mat_long_brand_cust", workloads.brand_cells, oracle.BRAND),
    ("doc_tf_cells", workloads.doc_cells, oracle.DOC),
    ("page_tf_cells", workloads.page_cells, oracle.PAGE),
    ("conv_tf_cells", workloads.conv_cells, oracle.CONV),
    ("part_month_cells", workloads.month_cells, oracle.MONTH.format("l_partkey")),
    ("user_day_cells", workloads.day_cells, oracle.DAY),
    ("user_etype_hour_cells", workloads.etype_hour_cells, "SELECT event_type || ':' || hour(ts)::VARCHAR AS r, user_id AS c, count(*)::DOUBLE AS v FROM events GROUP BY ALL"),
):
    query(f"SELECT r AS row_key, c AS col_key, v AS value FROM ({_sql})", _name)(_cells(_f, "row_key", "col_key", "value"))


@query("SELECT r AS feature, count(*) AS n, round(sum(v), 2) AS total FROM (SELECT 'l_quantity' AS r, l_quantity AS v FROM lineitem UNION ALL SELECT 'l_discount', l_discount FROM lineitem UNION ALL SELECT 'l_tax', l_tax FROM lineitem) GROUP BY r")
def li_numeric_features(spark, d):
    items = load(spark, d, "lineitem", "l_quantity", "l_discount", "l_tax")
    return items.unpivot([], ["l_quantity", "l_discount", "l_tax"], "feature", "v").groupBy("feature").agg(F.count("*").alias("n"), F.round(F.sum("v"), 2).alias("total"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS norm_sq FROM embeddings")
def mat_dense_emb_norms(spark, d):
    return workloads.emb(spark, d).df.select(F.col("col_id").alias("vec_id"), F.round(vec.norm_sq(F.col("vec")), 6).alias("norm_sq"))


@query(f"SELECT r AS term, count(*) AS n_docs, sum(v * v) AS norm_sq FROM ({oracle.DOC}) GROUP BY r")
def transpose_terms(spark, d):
    a, names = matrix.from_cells(workloads.doc_cells(spark, d), transpose=True)
    norms = a.cells.groupBy("col_id").agg(F.count("*").alias("n_docs"), F.sum(F.col("value") * F.col("value")).alias("norm_sq"))
    return norms.join(names, "col_id").select(F.col("key").alias("term"), "n_docs", "norm_sq")


@query(f"SELECT DISTINCT doc_id FROM documents WHERE doc_id NOT IN (SELECT c FROM ({oracle.DOC}))")
def zero_columns(spark, d):
    filled = relational.zero_fill(load(spark, d, "documents", "doc_id").distinct(), workloads.doc_cells(spark, d).withColumnRenamed("col_key", "doc_id"), "doc_id", "value")
    return filled.where("value = 0").select("doc_id")


@query(f"WITH s AS (SELECT c, string_agg(r || ':' || v::VARCHAR, ',' ORDER BY r) AS s FROM ({oracle.DOC}) GROUP BY c) SELECT c AS doc_id, f AS first_id FROM (SELECT c, min(c) OVER (PARTITION BY s) AS f FROM s) WHERE c != f")
def duplicate_columns(spark, d):
    a, names = matrix.from_cells(workloads.doc_cells(spark, d))
    pairs = matrix.duplicates(a)
    named = names.select(F.col("key").alias("doc_id"), "col_id")
    return pairs.join(named, "col_id").join(named.withColumnsRenamed({"doc_id": "first", "col_id": "first_id"}), "first_id").select("doc_id", F.col("first").alias("first_id"))


# Gram matrix and criterion


def _brand(spark, d):
    return matrix.from_cells(workloads.brand_cells(spark, d))


def _named(rows: DataFrame, names: DataFrame, *columns: str) -> DataFrame:
    for c in columns:
        rows = rows.join(F.broadcast(names.select(F.col("key").alias(f"{c}_key"), F.col("col_id").alias(c))), c).drop(c).withColumnRenamed(f"{c}_key", c)
    return rows


_GRAM = f"c AS MATERIALIZED ({oracle.BRAND}), g AS MATERIALIZED (SELECT a.c AS p, b.c AS q, sum(a.v * b.v) AS v FROM c a JOIN c b USING (r) GROUP BY ALL)"


@query(f"WITH {_GRAM} SELECT p, q, v FROM g WHERE p <= q")
def gram_brand(spark, d):
    a, names = _brand(spark, d)
    return _named(gram.gram_long(a), names, "p", "q").select(F.least("p", "q").alias("p"), F.greatest("p", "q").alias("q"), "v")


def _full_gram(spark, d):
    a, names = _brand(spark, d)
    half = gram.gram_long(a).persist(StorageLevel.MEMORY_AND_DISK)  # read several times
    return half.unionByName(half.where("p != q").select(F.col("q").alias("p"), F.col("p").alias("q"), "v")), names


@query(f"SELECT c AS brand, sum(v * v) AS norm_sq, count(*) AS n FROM ({oracle.BRAND}) GROUP BY c")
def colnorm_brand(spark, d):
    return workloads.brand_cells(spark, d).groupBy(F.col("col_key").alias("brand")).agg(F.sum(F.col("value") * F.col("value")).alias("norm_sq"), F.count("*").alias("n"))


@query(f"WITH {_GRAM} SELECT p AS brand, round(sum(v * v) / sum(v) FILTER (WHERE p = q), 3) AS explained FROM g GROUP BY p")
def criterion_single(spark, d):
    g, names = _full_gram(spark, d)
    return _named(g.groupBy("p").agg(F.round(F.sum(F.col("v") * F.col("v")) / F.sum(F.when(F.col("p") == F.col("q"), F.col("v"))), 3).alias("explained")), names, "p").withColumnRenamed("p", "brand")


@query(f"""WITH {_GRAM}, h AS (SELECT a.p, b.p AS q, sum(a.v * b.v) AS v FROM g a JOIN g b USING (q) GROUP BY ALL)
SELECT x.p, x.q, round((gq.v * hp.v - 2 * x.v * hx.v + gp.v * hq.v) / (gp.v * gq.v - x.v * x.v), 2) AS explained FROM g x JOIN g gp ON gp.p = x.p AND gp.q = x.p JOIN g gq ON gq.p = x.q AND gq.q = x.q
JOIN h hp ON hp.p = x.p AND hp.q = x.p JOIN h hq ON hq.p = x.q AND hq.q = x.q JOIN h hx ON hx.p = x.p AND hx.q = x.q WHERE x.p < x.q""")
def criterion_pairs_exhaustive(spark, d):
    g, names = _full_gram(spark, d)
    h = g.alias("a").join(g.alias("b"), F.col("a.q") == F.col("b.q")).groupBy(F.col("a.p").alias("p"), F.col("b.p").alias("q")).agg(F.sum(F.col("a.v") * F.col("b.v")).alias("h"))
    x = g.join(h, ["p", "q"])
    own = x.where("p = q")
    both = x.join(own.select("p", F.col("v").alias("gp"), F.col("h").alias("hp")), "p").join(own.select("q", F.col("v").alias("gq"), F.col("h").alias("hq")), "q")
    pairs = _named(both.withColumn("explained", F.expr("round((gq * hp - 2 * v * h + gp * hq) / (gp * gq - v * v), 2)")).select("p", "q", "explained"), names, "p", "q")
    return pairs.where("p < q").select("p", "q", "explained")


# Greedy selection


def _steps(selection: DataFrame, names: DataFrame, left: bool = True) -> DataFrame:
    rows = selection.join(F.broadcast(names), "col_id")
    return rows.select("step", "key", F.round("score", 3).alias("score"), (F.round("residual_sq", 3) if left else F.lit(None).cast("double")).alias("residual_sq"))


def _greedy(cells, l=5, **options):
    def run(spark, d):
        a, names = matrix.from_cells(cells(spark, d))
        return _steps(greedy.greedy_select(a, l, **options), names)

    return run


query(oracle.greedy(oracle.BRAND, 5), "greedy_brand_l5")(_greedy(workloads.brand_cells))
query(oracle.greedy(oracle.MONTH.format("l_suppkey"), 5), "greedy_supp_month_l5")(_greedy(lambda s, d: workloads.month_cells(s, d, "l_suppkey"), form="rowspace"))
query(oracle.greedy(oracle.DAY, 5), "greedy_user_day_l5")(_greedy(workloads.day_cells, form="rowspace"))


@query(oracle.greedy(oracle.MONTH.format("l_suppkey"), 4, start="(SELECT min(c) FROM n)"))
def greedy_warm_start(spark, d):
    a, names = matrix.from_cells(workloads.month_cells(spark, d, "l_suppkey"))
    return _steps(greedy.greedy_select(a, 4, "rowspace", start=[0]), names)


@query(oracle.greedy(oracle.BRAND, 4, score="norm"))
def pivoted_qr_brand(spark, d):
    a, names = _brand(spark, d)
    return _steps(baselines.pivoted_qr_select(a, 4), names, left=False)


_SUPP = f"SELECT r, c, v, dense_rank() OVER (ORDER BY c) - 1 AS i FROM ({oracle.MONTH.format('l_suppkey')})"


@query(oracle.greedy(f"SELECT r, c, v FROM ({_SUPP})", 4, target=oracle.sketch(_SUPP, 8, "sign")))
def greedy_target_sketch(spark, d):
    a, names = matrix.from_cells(workloads.month_cells(spark, d, "l_suppkey"))
    b = sketch.publish(sketch.sketch_columns(a, 8, "sign", combine="partial_agg"), a.m, 8)
    return _steps(greedy.greedy_select_for(a, b, 4), names)


@query(oracle.greedy(oracle.MONTH.format("l_suppkey"), 3))
def greedy_target_self(spark, d):
    a, names = matrix.from_cells(workloads.month_cells(spark, d, "l_suppkey"))
    return _steps(greedy.greedy_select_for(a, a, 3), names)


@query("WITH s AS (" + oracle.greedy(oracle.BRAND, 5) + ") SELECT step, round(residual_sq, 1) AS residual_sq FROM s WHERE step = 5")
def residual_after_selection(spark, d):
    a, _ = _brand(spark, d)
    s = greedy.greedy_select(a, 5)
    return spark.createDataFrame([(5, round(measures.residual_sq(a, s), 1))], "step int, residual_sq double")


@query("WITH s AS (" + oracle.greedy(oracle.BRAND, 5) + ") SELECT step, round(sum(score) OVER (ORDER BY step), 1) AS explained FROM s")
def telescoped_gain(spark, d):
    a, _ = _brand(spark, d)
    s = greedy.greedy_select(a, 5)
    return s.select("step", F.round(F.sum("gain").over(Window.orderBy("step")), 1).alias("explained"))


# Sketches


def _sketch_sql(cells: str, r: int, kind: str) -> str:
    return f"SELECT r AS row_key, k, v FROM ({oracle.sketch(f'SELECT r, v, dense_rank() OVER (ORDER BY c) - 1 AS i FROM ({cells})', r, kind)})"


def _sketch(cells, r, law):
    def run(spark, d):
        found = cells(spark, d)
        cols = matrix.keys(found, "col_key", "col_id").withColumnRenamed("key", "col_key")
        long = found.join(cols, "col_key").select(F.col("row_key").alias("row_id"), "col_id", "value")
        return sketch.sketch_long(long, r, law).select(F.col("row_id").alias("row_key"), F.col("k").cast("long").alias("k"), "v")

    return run


query(_sketch_sql(oracle.BRAND, 6, "sign"), "sketch_sign_brand")(_sketch(workloads.brand_cells, 6, "sign"))
query(_sketch_sql(oracle.MONTH.format("l_partkey"), 8, "sparse"), "sketch_sparse_sign_part_month")(_sketch(workloads.month_cells, 8, "sparse_sign"))


@query(_sketch_sql(f"SELECT {oracle.md5_number('r')} % 256 AS r, c, sum(v) AS v FROM ({oracle.counts('documents', 'doc_id', 'text', 0)}) GROUP BY ALL", 4, "sparse"))
def sketch_doc_hash(spark, d):
    counts = text.hash_rows(text.counts(load(spark, d, "documents", "doc_id", "text"), "doc_id", F.col("text")), 256)
    return _sketch(lambda s, d: counts, 4, "sparse_sign")(spark, d)


@query()
def sketch_gaussian_emb(spark, d):
    return sketch.sketch_columns(workloads.emb(spark, d), 16, "gaussian")


@query()
def sketch_error_ratio(spark, d):
    a = workloads.emb(spark, d)
    rows = []
    for law in random_maps.LAWS:
        b = sketch.publish(sketch.sketch_columns(a, 100, law), a.m, 100)
        energy = 3.0 if law == "sparse_sign" else 1.0
        rows.append((law, measures.sketch_error_ratio(a, greedy.greedy_select(a, 8, "rowspace"), b, energy / 100)))
    return spark.createDataFrame(rows, "law string, ratio double")


# Distributed selection and baselines






@query()
def two_stage_docs(spark, d):
    return distributed.two_stage_select(workloads.doc_hash(spark, d), 20, 100)






@query()
def greedy_doc_hash_l10(spark, d):
    return greedy.greedy_select(workloads.doc_hash(spark, d, 256), 10, "rowspace")


@query()
def block_greedy_emb(spark, d):
    return greedy.block_greedy(workloads.emb(spark, d), 12, 4)






@query(f"SELECT vec_id AS col_id, {oracle.md5_number(chr(39) + 'u' + chr(39), '0', 'vec_id')} AS h FROM embeddings ORDER BY 2, 1 LIMIT 20")
def uniform_hash_sample(spark, d):
    return baselines.uniform_ids(workloads.emb(spark, d).df, 20)


@query(f"WITH n AS (SELECT c, sum(v * v) AS p FROM ({_SUPP}) GROUP BY c), i AS (SELECT dense_rank() OVER (ORDER BY c) - 1 AS i, p FROM n) SELECT i AS col_id, round(-ln(({oracle.md5_number(chr(39) + 'w' + chr(39), '0', 'i')} + 0.5) / 4294967296.0) / p * 1e6, 6) AS key FROM i ORDER BY 2, 1 LIMIT 10")
def two_phase_colnorm_sample(spark, d):
    a, _ = matrix.from_cells(workloads.month_cells(spark, d, "l_suppkey"))
    return baselines.weighted_ids(baselines.probabilities(a, "colnorm", 10), 10).select("col_id", F.round(F.col("key") * 1e6, 6).alias("key"))


for _name, _f in {
    "two_phase_leverage": lambda a: baselines.two_phase_select(a, 10, "leverage"),
    "two_phase_strong": lambda a: baselines.two_phase_select(a, 10, "leverage", "strong_rrqr", cut_on="right_vectors"),
    "strong_rrqr_emb": lambda a: baselines.strong_rrqr_select(a, 10),
    "svd_target_emb": lambda a: baselines.svd_target_select(a, 10),
    "svd_target_exact_emb": lambda a: baselines.svd_target_select(a, 10, exact=True),
    "svd_target_distributed_emb": lambda a: baselines.distributed_svd_target_select(a, 10, 64, blocks="hash", n_blocks=4),
    "sketch_target_emb": lambda a: baselines.sketch_target_select(a, 10),
    "kmeans_nearest_emb": lambda a: baselines.kmeans_nearest_select(a, 10),
    "kmedoids_emb": lambda a: baselines.kmedoids_select(a, 10),
    "lsa_emb": lambda a: baselines.lsa_embed(a, 5),
    "randomized_svd_emb": lambda a: a.spark.createDataFrame([(i, float(x)) for i, x in enumerate(svd.randomized_svd(a, 10).values)], "i int, sigma double"),
    "embed_emb": lambda a: lowrank.embed(a, measures.ids_of(greedy.greedy_select(a, 8, "rowspace"))).df,
    "rank_k_emb": lambda a: lowrank.approximate_rank_k(a, measures.ids_of(greedy.greedy_select(a, 8, "rowspace")), 4).df,
    "approx_svd_emb": lambda a: lowrank.approx_svd_from_columns(a, measures.ids_of(greedy.greedy_select(a, 8, "rowspace")), 4)[2],
}.items():
    query(name=_name)(lambda s, d, f=_f: f(workloads.emb(s, d)))




_T2 = "WITH s AS ({0}), {1}, i AS (SELECT min(key) FILTER (WHERE step = 1) AS a, min(key) FILTER (WHERE step = 2) AS b FROM s)".format(oracle.greedy(oracle.BRAND, 2), _GRAM)


@query(_T2 + """, m AS (SELECT (SELECT v FROM g WHERE p = a AND q = a) AS aa, (SELECT v FROM g WHERE p = a AND q = b) AS ab, (SELECT v FROM g WHERE p = b AND q = b) AS bb, a, b FROM i)
SELECT x.q AS brand, round((bb * x.v - ab * y.v) / (aa * bb - ab * ab), 6) AS t1, round((aa * y.v - ab * x.v) / (aa * bb - ab * ab), 6) AS t2 FROM m JOIN g x ON x.p = m.a JOIN g y ON y.p = m.b AND y.q = x.q""")
def coefficients_l2(spark, d):
    a, names = _brand(spark, d)
    t = lowrank.coefficients(a, measures.ids_of(greedy.greedy_select(a, 2))).df
    # "+ 0.0" turns a negative zero into zero
    return t.join(F.broadcast(names), "col_id").select(F.col("key").alias("brand"), (F.round(F.col("vec")[0], 6) + 0.0).alias("t1"), (F.round(F.col("vec")[1], 6) + 0.0).alias("t2"))


@query()
def relative_accuracy_emb(spark, d):
    a = workloads.emb(spark, d)
    a = workloads.cached(a)
    found = {k: f(a, 10, 0) for k, f in {**workloads.CENTRAL, "two_stage": workloads.DISTRIBUTED["two_stage_sparse"]}.items()}
    return measures.rank_methods(measures.relative_accuracy(a, found, 10))


for _name, _run in workloads.WORKLOADS.items():
    query(name=_name)(lambda s, d, f=_run: f(s, d))


# Relational operators around the methods






_BIG = "SELECT o_custkey FROM orders WHERE o_totalprice > 300000"


def _big_customers(spark, d):
    return load(spark, d, "orders", "o_custkey", "o_totalprice").where("o_totalprice > 300000").select(F.col("o_custkey").alias("col_id")).distinct()


@query(f"SELECT c_custkey FROM customer WHERE c_custkey IN ({_BIG})")
def op_semi(spark, d):
    return relational.chosen(load(spark, d, "customer", "c_custkey"), _big_customers(spark, d), "c_custkey")


@query(f"SELECT c_custkey FROM customer WHERE c_custkey NOT IN ({_BIG})")
def op_anti(spark, d):
    return relational.unchosen(load(spark, d, "customer", "c_custkey"), _big_customers(spark, d), "c_custkey")


@query("SELECT a.event_id, (SELECT b.event_id FROM events b WHERE b.event_type = 'purchase' AND b.user_id = a.user_id AND b.ts <= a.ts ORDER BY b.ts DESC, b.event_id DESC LIMIT 1) IS NOT NULL AS after_purchase FROM events a WHERE a.event_type = 'click'")
def op_asof(spark, d):
    events = load(spark, d, "events", "event_id", "user_id", "ts", "event_type")
    clicks = events.where("event_type = 'click'").select("event_id", "user_id", "ts")
    bought = events.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase"))
    return relational.asof_join(clicks, bought, "user_id", "ts", "purchase").select("event_id", F.col("purchase").isNotNull().alias("after_purchase"))


@query("SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND epoch_us(b.ts) >= epoch_us(a.ts) AND epoch_us(b.ts) < epoch_us(a.ts) + 3600000000")
def op_range_join(spark, d):
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    events = load(spark, d, "events", "event_id", "user_id", "ts", "event_type")
    a = events.where("event_type = 'click'").select("user_id", at.alias("a_ts"), F.col("event_id").alias("click"))
    b = events.where("event_type = 'purchase'").select("user_id", at.alias("b_ts"), F.col("event_id").alias("purchase"))
    return relational.range_join(a, b, "user_id", "a_ts", "b_ts", 3_600_000_000).select("click", "purchase")


_ENERGY = "SELECT n_name, c_mktsegment, {0} AS level, count(*) AS n, round(sum(c_acctbal), 2) AS total FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY {1}"


def _customers(spark, d):
    return load(spark, d, "customer", "c_nationkey", "c_mktsegment", "c_acctbal").join(F.broadcast(load(spark, d, "nation", "n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey"))


@query(_ENERGY.format("grouping_id(n_name, c_mktsegment)", "CUBE (n_name, c_mktsegment)"))
def op_cube(spark, d):
    return _customers(spark, d).cube("n_name", "c_mktsegment").agg(F.grouping_id().cast("long").alias("level"), F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))


@query(_ENERGY.format("grouping_id(n_name, c_mktsegment)", "ROLLUP (n_name, c_mktsegment)"))
def op_rollup(spark, d):
    return _customers(spark, d).rollup("n_name", "c_mktsegment").agg(F.grouping_id().cast("long").alias("level"), F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))


@query(_ENERGY.format("grouping_id(n_name, c_mktsegment)", "GROUPING SETS ((n_name), (c_mktsegment), ())"))
def op_grouping_sets(spark, d):
    n, s = F.col("n_name"), F.col("c_mktsegment")
    return _customers(spark, d).groupingSets([[n], [s], []], n, s).agg(F.grouping_id().cast("long").alias("level"), F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))


@query("SELECT user_id, day, n, sum(n) OVER (PARTITION BY user_id ORDER BY day ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS moving, lag(n) OVER (PARTITION BY user_id ORDER BY day) AS before FROM (SELECT user_id, strftime(ts, '%Y-%m-%d') AS day, count(*) AS n FROM events GROUP BY ALL)")
def op_window_frames(spark, d):
    n = load(spark, d, "events", "user_id", "ts").groupBy("user_id", F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("n"))
    w = Window.partitionBy("user_id").orderBy("day")
    return n.withColumn("moving", F.sum("n").over(w.rowsBetween(-2, 0))).withColumn("before", F.lag("n").over(w))


@query("SELECT p_brand, p_partkey, p_retailprice FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS k FROM part) WHERE k <= 3")
def op_topk_group(spark, d):
    return relational.topk(load(spark, d, "part", "p_brand", "p_partkey", "p_retailprice"), ["p_brand"], [F.desc("p_retailprice"), F.col("p_partkey")], 3)


_USER_DAY = "SELECT user_id, strftime(ts, '%Y-%m-%d') AS day FROM events WHERE event_type = '{0}'"


@query("(" + " INTERSECT ".join(_USER_DAY.format(e) for e in ("click", "purchase")) + ") EXCEPT " + _USER_DAY.format("error"))
def op_set_ops(spark, d):
    e = load(spark, d, "events", "user_id", "ts", "event_type").withColumn("day", F.date_format("ts", "yyyy-MM-dd"))
    part = lambda c: e.where(F.col("event_type") == c).select("user_id", "day")
    return part("click").intersect(part("purchase")).subtract(part("error"))


@query("SELECT (props::JSON->>'k')::BIGINT AS k, count(*) AS n FROM events GROUP BY 1")
def op_json(spark, d):
    return load(spark, d, "events", "props").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"))


@query("SELECT doc_id, len(t) AS n, len(list_distinct(t)) AS n_distinct, t[1] AS first FROM (SELECT doc_id, regexp_extract_all(lower(text), '[a-z]+') AS t FROM documents) WHERE len(t) > 0")
def op_array(spark, d):
    t = load(spark, d, "documents", "doc_id", "text").select("doc_id", text.tokens(F.col("text")).alias("t")).where(F.size("t") > 0)
    return t.select("doc_id", F.size("t").cast("long").alias("n"), F.size(F.array_distinct("t")).cast("long").alias("n_distinct"), F.col("t")[0].alias("first"))


@query("SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(*) FILTER (WHERE event_type = 'purchase') AS purchases FROM events GROUP BY user_id")
def op_pivot(spark, d):
    n = load(spark, d, "events", "user_id", "event_type").groupBy("user_id").pivot("event_type", ["click", "purchase"]).count()
    return n.select("user_id", F.coalesce("click", F.lit(0)).cast("long").alias("clicks"), F.coalesce("purchase", F.lit(0)).cast("long").alias("purchases"))


@query("SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n, round(sum(o_totalprice), 1) AS total FROM orders GROUP BY ALL")
def op_dates(spark, d):
    return load(spark, d, "orders", "o_orderdate", "o_totalprice").groupBy(F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m")).agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 1).alias("total"))


@query("SELECT upper(substr(p_name, 1, 3)) AS head, count(*) AS n, sum(length(p_name))::BIGINT AS chars FROM part WHERE p_name LIKE '%a%' GROUP BY 1")
def op_strings(spark, d):
    return load(spark, d, "part", "p_name").where(F.col("p_name").like("%a%")).groupBy(F.upper(F.substring("p_name", 1, 3)).alias("head")).agg(F.count("*").alias("n"), F.sum(F.length("p_name")).alias("chars"))


@query("""WITH e AS (SELECT user_id, ts, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w < 1800000000 THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e) SELECT user_id, count(DISTINCT s) AS sessions, count(*) AS n FROM s GROUP BY user_id""")
def op_session_window(spark, d):
    e = load(spark, d, "events", "user_id", "ts").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count("*").alias("c")).groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("c").alias("n"))


@query(f"SELECT {oracle.md5_number(chr(39) + 's' + chr(39), 'o_orderkey')} % 100 AS bucket, count(*) AS n FROM orders GROUP BY 1 HAVING bucket < 10")
def op_hash_sample(spark, d):
    return load(spark, d, "orders", "o_orderkey").select((random_maps.hashed(F.lit("s"), F.col("o_orderkey")) % 100).alias("bucket")).where("bucket < 10").groupBy("bucket").agg(F.count("*").alias("n"))


@query("SELECT lang, count(*) AS n, count(toxic) AS chosen FROM documents LEFT JOIN (SELECT * FROM labels WHERE toxic = 1) USING (doc_id) GROUP BY lang")
def op_coverage(spark, d):
    docs = load(spark, d, "documents", "doc_id", "lang").withColumnRenamed("doc_id", "col_id")
    return measures.coverage_by(load(spark, d, "labels", "doc_id", "toxic").where("toxic = 1").withColumnRenamed("doc_id", "col_id"), docs, "lang")


@query("SELECT a.n_name AS n_name, b.n_name AS n_name_other FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey")
def op_pairs(spark, d):
    nations = load(spark, d, "nation", "n_nationkey", "n_regionkey", "n_name")
    return relational.pairs(nations, "n_nationkey", F.col("n_regionkey") == F.col("n_regionkey_other")).select("n_name", "n_name_other")


@query(f"SELECT c AS conv_id, r AS term, v::BIGINT AS n FROM (SELECT *, row_number() OVER (PARTITION BY c ORDER BY v DESC, r) AS k FROM ({oracle.counts('conversations', 'conv_id', 'text', 0)})) WHERE k <= 3")
def op_top_terms(spark, d):
    found = relational.top_terms(text.counts(load(spark, d, "conversations", "conv_id", "text"), "conv_id", F.col("text")), 3)
    return found.select(F.col("col_key").alias("conv_id"), F.col("row_key").alias("term"), F.col("value").cast("long").alias("n"))


@query("SELECT conv_id, count(*) AS n FROM (SELECT conv_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM conversations) GROUP BY conv_id")
def op_lateral(spark, d):
    load(spark, d, "conversations", "conv_id", "text").createOrReplaceTempView("lateral_texts")
    return spark.sql("SELECT conv_id, count(*) AS n FROM lateral_texts, LATERAL explode(regexp_extract_all(lower(text), '[a-z]+', 0)) AS t(w) GROUP BY conv_id")


@query("SELECT r AS token, sum(v)::BIGINT AS n FROM (" + oracle.counts("conversations", "conv_id", "text", 0) + ") GROUP BY r")
def op_tokens(spark, d):
    udfs.register(spark)
    load(spark, d, "conversations", "text").createOrReplaceTempView("token_texts")
    return spark.sql("SELECT token, count(*) AS n FROM token_texts, LATERAL tokens(text) GROUP BY token")


@query(f"SELECT i, k::INTEGER AS k, {oracle.law('sparse', oracle.md5_number('7', 'i', 'k'))}::DOUBLE AS w FROM (SELECT s_suppkey AS i FROM supplier), range(1, 13) t(k) WHERE w != 0")
def op_omega_row(spark, d):
    udfs.register(spark)
    load(spark, d, "supplier", "s_suppkey").createOrReplaceTempView("omega_ids")
    return spark.sql("SELECT s_suppkey AS i, k, w FROM omega_ids, LATERAL omega_row(7, s_suppkey, 12)")


@query(f"SELECT label, round(sum(v * v), 4) AS norm_sq FROM (SELECT label, r, sum(v) AS v FROM ({oracle.EMB.replace('vec_id AS c,', 'vec_id AS c, label,')}) GROUP BY ALL) GROUP BY label")
def op_vec_sum(spark, d):
    rows = load(spark, d, "embeddings", "embedding", "label").select("label", F.transform("embedding", lambda x: x.cast("double")).alias("vec"))
    return rows.groupBy("label").agg(udfs.vec_sum("vec").alias("s")).select("label", F.round(vec.norm_sq(F.col("s")), 4).alias("norm_sq"))


@query(f"SELECT label, round(sum(v), 4) AS trace FROM (SELECT label, v * v AS v FROM ({oracle.EMB.replace('vec_id AS c,', 'vec_id AS c, label,')})) GROUP BY label")
def op_gram_of(spark, d):
    rows = load(spark, d, "embeddings", "embedding", "label").select("label", F.transform("embedding", lambda x: x.cast("double")).alias("vec"))
    g = rows.groupBy("label").agg(udfs.gram_of("vec").alias("g"))
    diagonal = F.aggregate(F.filter("g", lambda x, i: i % 65 == 0), F.lit(0.0), lambda s, x: s + x)
    return g.select("label", F.round(diagonal, 4).alias("trace"))


@query(f"WITH s AS MATERIALIZED ({oracle.greedy(oracle.MONTH.format('l_suppkey'), 1)}), c AS MATERIALIZED ({oracle.MONTH.format('l_suppkey')}), d AS (SELECT x.c, sum(x.v * y.v) AS v FROM c x JOIN (SELECT r, v FROM c WHERE c = (SELECT key FROM s)) y USING (r) GROUP BY x.c) SELECT c AS key, round(sum(v * v) - coalesce(any_value(p), 0), 2) AS error FROM c LEFT JOIN (SELECT c, v * v / (SELECT sum(v * v) FROM c WHERE c = (SELECT key FROM s)) AS p FROM d) USING (c) GROUP BY c HAVING c != (SELECT key FROM s)")
def op_project_error(spark, d):
    a, names = matrix.from_cells(workloads.month_cells(spark, d, "l_suppkey"))
    one = greedy.greedy_select(a, 1)
    error = udfs.project_error(lowrank.basis(a, measures.ids_of(one)))
    rows = relational.unchosen(a.df.select("col_id", F.round(error("vec"), 2).alias("error")), one)
    return rows.join(F.broadcast(names), "col_id").select("key", "error")


@query("SELECT user_id, map_keys AS kinds, clicks FROM (SELECT user_id, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS map_keys, count(*) FILTER (WHERE event_type = 'click') AS clicks FROM events GROUP BY user_id)")
def op_map(spark, d):
    n = load(spark, d, "events", "user_id", "event_type").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.array_join(F.array_sort(F.map_keys("m")), ",").alias("kinds"), F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).cast("long").alias("clicks"))


@query("SELECT 'orders' AS what, true AS near UNION ALL SELECT 'median', true")
def op_approx(spark, d):
    """Approximate aggregates against exact ones: within three parts in a hundred.

    The exact count of keys is a query of its own: beside it, Spark would keep a
    sketch for every key.
    """
    items = load(spark, d, "lineitem", "l_orderkey", "l_quantity")
    exact = items.where("l_orderkey is not null").select("l_orderkey").distinct().agg(F.count("*").alias("exact"))
    near = items.agg(F.approx_count_distinct("l_orderkey", 0.01).alias("n"), (F.abs(F.percentile_approx("l_quantity", 0.5, 10000) - F.median("l_quantity")) <= 1).alias("median"))
    n = near.crossJoin(exact).select((F.abs(F.col("n") / F.col("exact") - 1) < 0.03).alias("orders"), "median")
    return n.unpivot([], ["orders", "median"], "what", "near")


@query("SELECT c_custkey FROM customer c WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer o WHERE o.c_nationkey = c.c_nationkey) AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c.c_custkey)")
def op_subquery(spark, d):
    load(spark, d, "customer", "c_custkey", "c_nationkey", "c_acctbal").createOrReplaceTempView("sub_customer")
    load(spark, d, "orders", "o_custkey").createOrReplaceTempView("sub_orders")
    return spark.sql("SELECT c_custkey FROM sub_customer c WHERE c_acctbal > (SELECT avg(c_acctbal) FROM sub_customer o WHERE o.c_nationkey = c.c_nationkey) AND EXISTS (SELECT 1 FROM sub_orders WHERE o_custkey = c.c_custkey)")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50 OFFSET 100")
def op_total_sort(spark, d):
    return relational.page(load(spark, d, "orders", "o_orderkey", "o_totalprice"), [F.desc("o_totalprice"), F.col("o_orderkey")], 100, 50)


@query("SELECT c_mktsegment, sum(c_acctbal) FILTER (WHERE c_nationkey = 1) AS n1, sum(c_acctbal) FILTER (WHERE c_nationkey = 2) AS n2 FROM (SELECT c_mktsegment, c_nationkey, round(sum(c_acctbal), 2) AS c_acctbal FROM customer GROUP BY ALL) GROUP BY c_mktsegment")
def op_wide(spark, d):
    sums = load(spark, d, "customer", "c_mktsegment", "c_nationkey", "c_acctbal").groupBy("c_mktsegment", F.concat(F.lit("n"), "c_nationkey").alias("n")).agg(F.round(F.sum("c_acctbal"), 2).alias("v"))
    return relational.wide(sums, "c_mktsegment", "n", "v", ["n1", "n2"])


@query("SELECT event_type, round(corr(value, hour(ts)), 8) AS corr, round(covar_samp(value, hour(ts)), 6) AS covar, round(regr_slope(value, hour(ts)), 8) AS slope, round(median(value), 4) AS median FROM events GROUP BY event_type")
def op_statistics(spark, d):
    e, h = load(spark, d, "events", "event_type", "value", "ts"), F.hour("ts")
    return e.groupBy("event_type").agg(F.round(F.corr("value", h), 8).alias("corr"), F.round(F.covar_samp("value", h), 6).alias("covar"), F.round(F.regr_slope("value", h), 8).alias("slope"), F.round(F.median("value"), 4).alias("median"))


@query("SELECT p_partkey, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, rank() OVER w AS place FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey)")
def op_rankings(spark, d):
    w = Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")
    return load(spark, d, "part", "p_brand", "p_partkey", "p_retailprice").select("p_partkey", F.ntile(4).over(w).cast("long").alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.rank().over(w).cast("long").alias("place"))


_MONTH = oracle.MONTH.format("l_suppkey")


@query(f"WITH a_ AS MATERIALIZED ({oracle.greedy(_MONTH, 4)}), b_ AS MATERIALIZED ({oracle.greedy(_MONTH, 4, score='norm')}) SELECT key, a_.step AS first, b_.step AS second FROM a_ FULL JOIN b_ USING (key)")
def op_full_outer(spark, d):
    a, names = matrix.from_cells(workloads.month_cells(spark, d, "l_suppkey"))
    return relational.compared(greedy.greedy_select(a, 4), baselines.pivoted_qr_select(a, 4)).join(F.broadcast(names), "col_id").select("key", "first", "second")


@query(f"WITH c AS MATERIALIZED ({twins.SUPP}), b AS MATERIALIZED ({oracle.sketch(twins.SUPP, 6, 'sign')}), f AS (SELECT c, sum(h * h) AS f FROM (SELECT c.c, k, sum(b.v * c.v) AS h FROM c JOIN b USING (r) GROUP BY ALL) GROUP BY c), g AS (SELECT c, sum(v * v) AS g FROM c GROUP BY c) SELECT s_nationkey::BIGINT AS nation, c AS key, round(f / g, 3) AS score FROM (SELECT *, row_number() OVER (PARTITION BY s_nationkey ORDER BY f / g DESC, c) AS k FROM f JOIN g USING (c) JOIN supplier ON c = s_suppkey) WHERE k = 1")
def op_cogroup(spark, d):
    """The best column of each nation for a common sketch: columns and their cross products meet group by group."""
    a, names = matrix.from_cells(workloads.month_cells(spark, d, "l_suppkey"))
    b = sketch.sketch_columns(a, 6, "sign", draws="hash")
    cross = matrix.to_long(a).join(b.select("row_id", F.posexplode("sketch").alias("k", "s")), "row_id").groupBy("col_id", "k").agg(F.sum(F.col("value") * F.col("s")).alias("v"))
    nation = names.join(load(spark, d, "supplier", "s_suppkey", "s_nationkey"), F.col("key") == F.col("s_suppkey")).select("col_id", F.col("s_nationkey").cast("long").alias("grp"))
    again = nation.select(F.col("col_id").alias("i"), F.col("grp").alias("g"))
    crossed = cross.join(again, F.col("col_id") == F.col("i")).select(F.col("g").alias("grp"), F.col("i").alias("col_id"), "k", "v")
    out = greedy.select_cogrouped(a.df.join(nation, "col_id"), crossed, 6, 1)
    return out.join(F.broadcast(names), "col_id").select(F.col("grp").alias("nation"), "key", F.round("score", 3).alias("score"))


# Streams over the events, read to their end


def _streamed(make, mode="complete"):
    return lambda spark, d: streams.replay(spark, f"{d}/events.parquet", lambda e: make(spark, d, e.withColumn("ts", F.col("ts").cast("timestamp"))), mode)


query("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, user_id, count(*)::DOUBLE AS value FROM events GROUP BY ALL", "stream_day_cells")(_streamed(lambda s, d, e: streams.cells(e, "1 day").select(F.date_format("start", "yyyy-MM-dd").alias("day"), "user_id", "value")))
query("SELECT strftime(time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '2024-01-01') - o * INTERVAL '6 hours', '%Y-%m-%d %H') AS start, user_id, count(*)::DOUBLE AS value FROM events, range(4) t(o) GROUP BY ALL", "stream_sliding_cells")(_streamed(lambda s, d, e: streams.cells(e, "1 day", "6 hours").select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "user_id", "value")))
query("""WITH e AS (SELECT user_id, ts, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w < 1800000000 THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e) SELECT user_id, count(DISTINCT s) AS sessions, count(*) AS n FROM s GROUP BY user_id""", "stream_sessions")(
    lambda spark, d: _streamed(lambda s, d, e: streams.sessions(e))(spark, d).groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))
)
query("SELECT DISTINCT event_id, user_id FROM events", "stream_dedup")(
    # every event comes twice; the second is dropped
    _streamed(lambda s, d, e: streams.dedup(streams.timed(e.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))))).select("event_id", "user_id"), "append")
)
query("SELECT event_id, user_id, c_name FROM events LEFT JOIN customer ON user_id = c_custkey WHERE event_type = 'purchase'", "stream_enrich")(
    _streamed(lambda s, d, e: streams.enrich(e.where("event_type = 'purchase'"), load(s, d, "customer", "c_custkey", "c_name").withColumnRenamed("c_custkey", "user_id"), "user_id").select("event_id", "user_id", "c_name"), "append")
)
query("SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL '1 hour'", "stream_within")(
    _streamed(lambda s, d, e: streams.within(streams.timed(e.where("event_type = 'click'")), streams.timed(e.where("event_type = 'purchase'")), "user_id", "1 hour").select(F.col("a_id").alias("click"), F.col("b_id").alias("purchase")), "append")
)
query(f"SELECT r AS row_id, k, v FROM ({oracle.sketch('SELECT event_type AS r, user_id AS i, 1.0::DOUBLE AS v FROM events', 6, 'sign')})", "stream_sketch")(
    _streamed(lambda s, d, e: streams.sketch_stream(e.select(F.col("event_type").alias("row_id"), F.col("user_id").alias("col_id"), F.lit(1.0).alias("value")), 6, "sign").select("row_id", F.col("k").cast("long").alias("k"), "v"))
)


twins.register(query)
