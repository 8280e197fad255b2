"""More registered queries: methods, baselines and measures on matrices whose results SQL can repeat.

Random numbers come from hashes that any engine has, blocks from hashes of ids,
so that the SQL says what the distributed plan must return, to the digit.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import oracle, workloads
from .functions import text, udfs, vec
from .operators import baselines, distributed, greedy, lowrank, matrix, measures, sketch, svd
from .operators.matrix import ColumnFrame
from .sources.tables import load

MONTH = oracle.MONTH.format("l_suppkey")
SUPP = oracle.ranked(MONTH)
DOC128 = f"SELECT {oracle.md5_number('r')} % 128 AS r, c, sum(v) AS v FROM ({oracle.counts('documents', 'doc_id', 'text', 0)}) GROUP BY ALL"
ITEM128 = f"SELECT {oracle.md5_number('r')} % 128 AS r, c AS k, sum(v) AS v FROM ({oracle.counts('benchmark', 'item_id', 'text', 0)}) GROUP BY ALL"


def supp(spark, d) -> tuple[ColumnFrame, DataFrame]:
    """Suppliers by month of shipping, and the dictionary of its columns."""
    return matrix.from_cells(workloads.month_cells(spark, d, "l_suppkey"))


def steps(selection: DataFrame, names: DataFrame | None = None, left: bool = True) -> DataFrame:
    """(step, key, score, residual_sq), rounded."""
    rows = selection.withColumn("key", F.col("col_id")) if names is None else selection.join(F.broadcast(names), "col_id")
    out = rows.select("step", "key", F.round("score", 3).alias("score"), F.round("residual_sq", 3).alias("residual_sq"))
    return out if left else out.drop("residual_sq")


def register(query) -> None:
    """Adds everything below to the catalog by its decorator."""
    for name, (sql, run) in {**_greedy(), **_two_stage(), **_baselines(), **_sketches(), **_low_rank(), **_measures(), **_uses()}.items():
        query(sql, name)(run)


# Greedy forms


def _greedy() -> dict:
    def scored(spark, d):
        a, names = supp(spark, d)
        return steps(greedy.greedy_select(a, 4, "scores"), names)

    def scored_for(b_of):
        def run(spark, d):
            a, names = supp(spark, d)
            b = sketch.publish(sketch.sketch_columns(a, 8, "sign", combine="partial_agg"), a.m, 8)
            return steps(greedy.greedy_select_for(a, b_of(a, b), 4, "scores"), names)

        return run

    def as_frame(a, b):
        """The sketch as columns, to be met by a join on the rows."""
        return ColumnFrame(a.spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(b.T)], "col_id long, vec array<double>"), a.m)

    def form(name, l=4, cells=None):
        def run(spark, d):
            a, names = supp(spark, d)
            return steps(greedy.greedy_select(a, l, name), names)

        return run

    def docs(spark, d):
        return steps(greedy.greedy_select(workloads.doc_hash(spark, d, 128), 8, "rowspace"))

    def for_items(spark, d):
        """Documents that span the benchmark's hashed token counts best."""
        items = text.hash_rows(text.counts(load(spark, d, "benchmark", "item_id", "text"), "item_id", F.col("text")), 128)
        b = matrix.pack(items.select(F.col("row_key").alias("row_id"), F.col("col_key").alias("col_id"), "value"), 128)
        return steps(greedy.greedy_select_for(workloads.doc_hash(spark, d, 128), b, 6))

    def terms(spark, d):
        a, names = matrix.from_cells(workloads.doc_cells(spark, d, 200), transpose=True)
        return steps(greedy.greedy_select(a, 6), names)

    def doc_tf(spark, d):
        a, names = matrix.from_cells(workloads.doc_cells(spark, d))
        return steps(greedy.greedy_select(a, 10, "rowspace"), names)

    def stop(spark, d):
        """Columns until a twentieth of the energy is left."""
        a, names = supp(spark, d)
        return steps(greedy.greedy_select(a, 20, "rowspace", rel_tol=0.05), names)

    target = oracle.sketch(SUPP, 8, "sign")
    in_target = oracle.greedy(f"SELECT r, c, v FROM ({SUPP})", 4, target=target)
    stopped = f"WITH s_ AS ({oracle.greedy_rows(MONTH, 20)}) SELECT * FROM s_ WHERE step <= (SELECT coalesce(min(step), 20) FROM s_ WHERE residual_sq <= 0.05 * (SELECT sum(v * v) FROM ({MONTH})))"
    return {
        "greedy_scores_supp": (oracle.greedy(MONTH, 4), scored),
        "greedy_scores_target": (in_target, scored_for(lambda a, b: b)),
        "greedy_scores_target_by_rows": (in_target, scored_for(as_frame)),
        "greedy_rowspace_target_frame": (in_target, lambda s, d: (lambda a, names: steps(greedy.greedy_select_for(a, as_frame(a, sketch.publish(sketch.sketch_columns(a, 8, "sign", combine="partial_agg"), a.m, 8)), 4), names))(*supp(s, d))),
        "greedy_residual_form": (oracle.greedy(MONTH, 4), form("residual")),
        "greedy_local_form": (oracle.greedy(MONTH, 4), form("local")),
        "greedy_naive_form": (oracle.greedy(MONTH, 3), form("naive", 3)),
        "greedy_stop_early": (stopped, stop),
        "greedy_emb_l10": (oracle.greedy_rows(oracle.EMB, 10), lambda s, d: steps(greedy.greedy_select(workloads.emb(s, d), 10, "rowspace"))),
        "greedy_doc_hash_l8": (oracle.greedy_rows(DOC128, 8), docs),
        "greedy_doc_tf_l10": (oracle.greedy_rows(oracle.DOC, 10), doc_tf),
        "docs_for_benchmark": (oracle.greedy_rows(DOC128, 6, ITEM128), for_items),
        "feature_terms": (oracle.greedy_rows(f"SELECT c AS r, r AS c, v FROM ({oracle.counts('documents', 'doc_id', 'text', 200)})", 6), terms),
    }


# Two passes


def _two_stage() -> dict:
    def run(l, quota, r=8, law="sparse_sign", cells=supp):
        def f(spark, d):
            a, names = cells(spark, d)
            return steps(distributed.two_stage_select(a, l, r, law, blocks="hash", n_blocks=4, quota=quota, draws="hash"), names)

        return f

    def union(refine, quota):
        def f(spark, d):
            a, names = supp(spark, d)
            return steps(distributed.local_union_select(a, 8, 4, refine=refine, quota=quota), names, refine)

        return f

    def any_target(spark, d):
        """Line items' months of suppliers, chosen for those of the parts' sketch."""
        a, names = supp(spark, d)
        b = sketch.publish(sketch.sketch_columns(a, 6, "sign", combine="partial_agg"), a.m, 6)
        return steps(distributed.two_stage_select(a, 5, 6, target=b, blocks="hash", n_blocks=4, quota="ceil"), names)

    def levels(spark, d):
        """The same choice merged in levels of two groups."""
        a, names = supp(spark, d)
        b = sketch.publish(sketch.sketch_columns(a, 6, "sign", combine="partial_agg"), a.m, 6)
        return steps(distributed.merged(distributed.choose_in_blocks(a, 3, b, "hash", 4), 5, b, a.m, fanin=2, n_groups=4), names)

    two = lambda l, l_b, kind="sparse", r=8: oracle.two_stage(SUPP, l, r, kind, 4, l_b)
    cells = f"SELECT r, c, v, i FROM ({SUPP})"
    ctes = ["cells_ AS MATERIALIZED (" + cells + ")", "sk_ AS MATERIALIZED (" + oracle.sketch("SELECT r, v, i FROM cells_", 6, "sign") + ")"]
    pick = lambda rows, l: oracle.greedy(rows, l, target="SELECT r, k, v FROM sk_")
    blocks = oracle.block_choices("cells_", 4, 3, "SELECT r, k, v FROM sk_")
    # groups of the next level: block modulo 2
    groups = [f"grp{k} AS MATERIALIZED ({pick(f'SELECT r, c, v FROM cells_ WHERE c IN (SELECT key FROM cand_ WHERE block % 2 = {k})', 5)})" for k in (0, 1)]
    both = "SELECT key FROM grp0 UNION ALL SELECT key FROM grp1"
    leveled = "WITH " + ",\n".join([*ctes, *blocks, *groups]) + "\nSELECT * FROM (" + pick(f"SELECT r, c, v FROM cells_ WHERE c IN ({both})", 5) + ")"
    given = "WITH " + ",\n".join([*ctes, *oracle.block_choices("cells_", 4, 2, "SELECT r, k, v FROM sk_")]) + "\nSELECT * FROM (" + pick("SELECT r, c, v FROM cells_ WHERE c IN (SELECT key FROM cand_)", 5) + ")"
    return {
        "two_stage_floor": (two(8, 2), run(8, "floor")),
        "two_stage_ceil": (two(6, 2), run(6, "ceil")),
        "two_stage_oversample": (two(8, 4), run(8, "oversample")),
        "two_stage_full": (two(5, 5), run(5, "full")),
        "two_stage_sign": (two(6, 3, "sign"), run(6, "oversample", law="sign")),
        "two_stage_levels": (leveled, levels),
        "two_stage_any_target": (given, any_target),
        "two_stage_emb": (oracle.two_stage(oracle.EMB_I, 10, 16, "sparse", 4, 5, oracle.greedy_rows), lambda s, d: steps(distributed.two_stage_select(workloads.emb(s, d), 10, 16, blocks="hash", n_blocks=4, draws="hash"))),
        "local_union": (oracle.local_union(SUPP, 8, 4, 2, False), union(False, "ceil")),
        "local_union_refined": (oracle.local_union(SUPP, 8, 4, 4, True), union(True, "oversample")),
    }


# Baselines


def _baselines() -> dict:
    l, s = 6, math.ceil(6 * math.log(6))
    ids = "SELECT c, i, sum(v * v) AS p FROM cells_ GROUP BY ALL"
    uniform = f"SELECT c FROM ({ids}) ORDER BY {oracle.md5_number(chr(39) + 'u' + chr(39), '0', 'i')}, i LIMIT {s}"
    weighted = f"SELECT c FROM ({ids}) ORDER BY -ln(({oracle.md5_number(chr(39) + 'w' + chr(39), '0', 'i')} + 0.5) / 4294967296.0) / p, i LIMIT {s}"

    def cut(sample, score="energy"):
        return f"WITH cells_ AS MATERIALIZED ({SUPP}), sample_ AS MATERIALIZED ({sample}) SELECT * {'EXCLUDE (residual_sq)' if score == 'norm' else ''} FROM (" + oracle.greedy("SELECT r, c, v FROM cells_ WHERE c IN (SELECT c FROM sample_)", l, score) + ")"

    def phases(prob, how, left=True):
        def run(spark, d):
            a, names = supp(spark, d)
            return steps(baselines.two_phase_select(a, l, prob, how), names, left)

        return run

    def sketch_target(spark, d):
        a, names = supp(spark, d)
        return steps(greedy.greedy_select_for(a, sketch.publish(sketch.sketch_columns(a, 5, "sparse_sign", draws="hash"), a.m, 5), 5), names)

    def exhaustive(spark, d):
        a, names = matrix.from_cells(workloads.brand_cells(spark, d))
        return baselines.exhaustive_select(a, 2).join(F.broadcast(names), "col_id").select("step", "key", F.round("gain", 1).alias("gain"), F.round("residual_sq", 1).alias("residual_sq"))

    def uniform_run(spark, d):
        rows = baselines.uniform_select(workloads.emb(spark, d), 10, 3)
        return rows.select("step", "col_id")

    gram = f"c AS MATERIALIZED ({oracle.BRAND}), g AS MATERIALIZED (SELECT a.c AS p, b.c AS q, sum(a.v * b.v) AS v FROM c a JOIN c b USING (r) GROUP BY ALL), h AS MATERIALIZED (SELECT a.p, b.p AS q, sum(a.v * b.v) AS v FROM g a JOIN g b USING (q) GROUP BY ALL)"
    best = f"""WITH {gram}, pairs AS (SELECT x.p, x.q, hp.v / gp.v AS first, (gq.v * hp.v - 2 * x.v * hx.v + gp.v * hq.v) / (gp.v * gq.v - x.v * x.v) AS gain FROM g x JOIN g gp ON gp.p = x.p AND gp.q = x.p JOIN g gq ON gq.p = x.q AND gq.q = x.q
JOIN h hp ON hp.p = x.p AND hp.q = x.p JOIN h hq ON hq.p = x.q AND hq.q = x.q JOIN h hx ON hx.p = x.p AND hx.q = x.q WHERE x.p < x.q ORDER BY gain DESC, x.p, x.q LIMIT 1), e AS (SELECT sum(v) AS v FROM g WHERE p = q)
SELECT 1 AS step, p AS key, round(first, 1) AS gain, round((SELECT v FROM e) - first, 1) AS residual_sq FROM pairs UNION ALL SELECT 2, q, round(gain - first, 1), round((SELECT v FROM e) - gain, 1) FROM pairs"""
    return {
        "two_phase_uniform_greedy": (cut(uniform), phases("uniform", "greedy")),
        "two_phase_colnorm_greedy": (cut(weighted), phases("colnorm", "greedy")),
        "two_phase_colnorm_qr": (cut(weighted, "norm"), phases("colnorm", "pivoted_qr", False)),
        "two_phase_uniform_qr": (cut(uniform, "norm"), phases("uniform", "pivoted_qr", False)),
        "sketch_target_supp": (oracle.greedy(f"SELECT r, c, v FROM ({SUPP})", 5, target=oracle.sketch(SUPP, 5, "sparse")), sketch_target),
        "exhaustive_brand_l2": (best, exhaustive),
        "uniform_emb": (f"SELECT row_number() OVER (ORDER BY h, vec_id) AS step, vec_id AS col_id FROM (SELECT vec_id, {oracle.md5_number(chr(39) + 'u' + chr(39), '3', 'vec_id')} AS h FROM embeddings) ORDER BY 1 LIMIT 10", uniform_run),
    }


# Sketches


def _sketches() -> dict:
    def long(frame, names_of_rows, scale=None):
        out = frame.select("row_id", F.posexplode("sketch").alias("k", "v")).select("row_id", (F.col("k") + 1).cast("long").alias("k"), "v")
        return out.join(names_of_rows, "row_id").select(F.col("key").alias("row_key"), "k", F.round("v", 4).alias("v"))

    def run(law, r, **options):
        def f(spark, d):
            cells = workloads.month_cells(spark, d, "l_suppkey")
            a, _ = matrix.from_cells(cells)
            return long(sketch.sketch_columns(a, r, law, **options), matrix.keys(cells, "row_key", "row_id")).where("v != 0")

        return f

    def merged(spark, d):
        cells = workloads.month_cells(spark, d, "l_suppkey")
        a, _ = matrix.from_cells(cells)
        halves = [sketch.sketch_columns(a.where(F.col("col_id") % 2 == k), 6, "sign", draws="hash") for k in (0, 1)]
        return long(sketch.merge(*halves), matrix.keys(cells, "row_key", "row_id")).where("v != 0")

    def sql(kind, r, s=3, scale=""):
        return f"SELECT r AS row_key, k, round(v{scale}, 4) AS v FROM ({oracle.sketch(SUPP, r, kind) if s == 3 else oracle.sketch(SUPP, r, kind).replace('% 6', f'% (2 * {s})')}) WHERE round(v{scale}, 4) != 0"

    u = lambda seed: f"(({oracle.md5_number(str(seed), 'i', 'k')} + 0.5) / 4294967296.0)"
    gaussian = f"SELECT r AS row_key, k, round(sum(v * w), 4) AS v FROM ({SUPP}) JOIN (SELECT i, k, sqrt(-2 * ln({u(0)})) * cos(2 * pi() * {u(1)}) AS w FROM (SELECT DISTINCT i FROM ({SUPP})), range(1, 5) t(k)) USING (i) GROUP BY ALL HAVING round(sum(v * w), 4) != 0"
    root = f"greatest(1, round(sqrt((SELECT count(DISTINCT i) FROM ({SUPP})))))::BIGINT"

    def volume(spark, d):
        a, _ = supp(spark, d)
        return measures.sketch_records(a, 8, tasks=4)

    drawn = f"SELECT i, k FROM (SELECT DISTINCT i FROM ({SUPP})), range(1, 9) t(k) WHERE {oracle.law('sparse', oracle.md5_number('0', 'i', 'k'))} != 0"
    return {
        "sketch_in_task_sign": (sql("sign", 6), run("sign", 6, draws="hash")),
        "sketch_in_task_sparse": (sql("sparse", 8), run("sparse_sign", 8, draws="hash")),
        "sketch_no_combiner": (sql("sign", 6), run("sign", 6, combine="none")),
        "sketch_scaled": (sql("sign", 4, scale=" / 2"), run("sign", 4, draws="hash", scale="1/sqrt(r)")),
        "sketch_sqrt_sparse": (sql("sparse", 8, root), run("sparse_sign", 8, draws="hash", s="sqrt")),
        "sketch_gaussian_supp": (gaussian, run("gaussian", 4, draws="hash")),
        "sketch_merged": (sql("sign", 6), merged),
        "sketch_volume": (f"SELECT 'none' AS combine, count(*) AS records FROM ({SUPP}) JOIN ({drawn}) USING (i) WHERE v != 0 UNION ALL SELECT 'in_task', 4 * count(DISTINCT r) FROM ({MONTH})", volume),
    }


# Low rank

_GRAM = f"c AS MATERIALIZED ({MONTH}), g AS MATERIALIZED (SELECT a.c AS p, b.c AS q, sum(a.v * b.v) AS v FROM c a JOIN c b USING (r) GROUP BY ALL)"
_PICKS = f"WITH s_ AS MATERIALIZED ({oracle.greedy(MONTH, 2)}), {_GRAM}, i AS (SELECT min(key) FILTER (WHERE step = 1) AS a, min(key) FILTER (WHERE step = 2) AS b FROM s_), m AS (SELECT (SELECT v FROM g WHERE p = a AND q = a) AS aa, (SELECT v FROM g WHERE p = a AND q = b) AS ab, (SELECT v FROM g WHERE p = b AND q = b) AS bb, a, b FROM i)"


def _two_picks(a):
    return measures.ids_of(greedy.greedy_select(a, 2))


def _low_rank() -> dict:
    def norms(of):
        def run(spark, d):
            a, names = supp(spark, d)
            rows = of(a, _two_picks(a)).df.select("col_id", F.round(vec.norm_sq(F.col("vec")), 1).alias("norm_sq"))
            return rows.join(F.broadcast(names), "col_id").select("key", "norm_sq")

        return run

    def rank_k(spark, d):
        """Energy of the best approximation of rank 1 in the span of two columns, and the leading value from them."""
        a, _ = supp(spark, d)
        ids = _two_picks(a)
        kept = lowrank.approximate_rank_k(a, ids, 1).df.agg(F.sum(vec.norm_sq(F.col("vec"))).alias("e")).first().e
        _, values, right = lowrank.approx_svd_from_columns(a, ids, 1)
        unit = right.agg(F.sum(F.col("v")[0] * F.col("v")[0]).alias("e")).first().e
        return spark.createDataFrame([(round(kept / 1e6, 4), round(float(values[0]) ** 2 / 1e6, 4), round(unit, 6))], "energy double, value_sq double, right_norm double")

    def values(spark, d):
        """Sums over the singular values: of squares, and of fourth powers as a share."""
        a, _ = supp(spark, d)
        s = svd.exact_svd(a).values
        e = float((s**2).sum())
        return spark.createDataFrame([(round(e, 1), round(float((s**4).sum()) / e**2, 9))], "energy double, fourth double")

    def leading(spark, d):
        """Share of the energy of the leading direction, exactly and at random, and what any matrix of rank 1 leaves."""
        a, _ = supp(spark, d)
        exact = svd.exact_svd(a).values
        e = float((exact**2).sum())
        at_random = svd.randomized_svd(a, 1, power=3).values[0]
        return spark.createDataFrame([(round(float(exact[0]) ** 2 / e, 7), round(float(at_random) ** 2 / e, 7), round(measures.best_rank_error(a, 1) / e**0.5, 6), round(measures.residual_norm(a, [], "spectral") / e**0.5, 6))], "exact double, randomized double, best_error double, spectral double")

    def lsa(spark, d):
        """Energy of the coordinates of all columns on all directions, one a direction."""
        a, _ = supp(spark, d)
        v = baselines.lsa_embed(a, a.m)
        kept = v.where(F.size("v") > 0).agg(F.sum(vec.norm_sq(F.col("v"))).alias("n")).first().n
        return spark.createDataFrame([(int(round(kept)),)], "directions int")

    energy = "(SELECT (bb * x.v * x.v - 2 * ab * x.v * y.v + aa * y.v * y.v) / (aa * bb - ab * ab) FROM g x, g y WHERE x.p = m.a AND x.q = k AND y.p = m.b AND y.q = k)"
    norm_sql = f"{_PICKS} SELECT k AS key, round({energy}, 1) AS norm_sq FROM m, (SELECT DISTINCT c AS k FROM c)"
    t = "(SELECT sum(x.v * y.v) FROM g x JOIN g y USING (q) WHERE x.p = {0} AND y.p = {1})"
    rank_sql = f"""{_PICKS}, t AS (SELECT m.*, {t.format('m.a', 'm.a')} AS taa, {t.format('m.a', 'm.b')} AS tab, {t.format('m.b', 'm.b')} AS tbb FROM m),
z AS (SELECT (bb * taa - 2 * ab * tab + aa * tbb) / (aa * bb - ab * ab) AS tr, (taa * tbb - tab * tab) / (aa * bb - ab * ab) AS det FROM t)
SELECT round((tr + sqrt(tr * tr - 4 * det)) / 2e6, 4) AS energy, round((tr + sqrt(tr * tr - 4 * det)) / 2e6, 4) AS value_sq, 1.0::DOUBLE AS right_norm FROM z"""
    lam = f"WITH {_GRAM}, {', '.join(oracle.top_value('g'))}"
    return {
        "embed_norms": (norm_sql, norms(lowrank.embed)),
        "project_norms": (norm_sql, norms(lowrank.project)),
        "approximate_norms": (norm_sql, norms(lowrank.approximate)),
        "rank_k_error": (rank_sql, rank_k),
        "svd_energies": (f"WITH {_GRAM} SELECT round((SELECT sum(v) FROM g WHERE p = q), 1) AS energy, round(sum(v * v) / pow((SELECT sum(v) FROM g WHERE p = q), 2), 9) AS fourth FROM g", values),
        "svd_leading": (f"{lam} SELECT round(share, 7) AS exact, round(share, 7) AS randomized, round(sqrt(1 - share), 6) AS best_error, round(sqrt(share), 6) AS spectral FROM lam", leading),
        "lsa_directions": (f"SELECT least(count(DISTINCT r), count(DISTINCT c))::INTEGER AS directions FROM ({MONTH})", lsa),
    }


# Measures


def _measures() -> dict:
    u = lambda seed: f"SELECT c FROM (SELECT DISTINCT c, i FROM cells_) ORDER BY {oracle.md5_number(chr(39) + 'u' + chr(39), str(seed), 'i')}, i LIMIT 1"
    ctes = f"cells_ AS MATERIALIZED ({SUPP}), {_GRAM}, {', '.join(oracle.top_value('g'))}, e AS (SELECT sum(v) AS v FROM g WHERE p = q), own AS MATERIALIZED (SELECT p, sqrt((SELECT v FROM e) - sum(v * v) / sum(v) FILTER (WHERE p = q)) AS err FROM g GROUP BY p)"
    draws = lambda seeds: " UNION ALL ".join(f"SELECT {s} AS seed, ({u(s)}) AS p" for s in seeds)
    ends = f"ref AS (SELECT avg(err) AS base FROM ({draws(range(1000, 1010))}) JOIN own USING (p)), low AS (SELECT sqrt((SELECT v FROM e) * (1 - share)) AS low FROM lam)"
    acc = "round(100 * (base - err) / (base - low), 4)"

    def one(spark, d):
        a, _ = supp(spark, d)
        found = {"greedy": greedy.greedy_select(a, 1), "pivoted_qr": baselines.pivoted_qr_select(a, 1), "uniform": baselines.uniform_select(a, 1, 5)}
        return measures.relative_accuracy(a, found, 1, 10, 1000)

    def accuracy(spark, d):
        return one(spark, d).select("method", "l", F.round("rel_acc", 4).alias("rel_acc"))

    def placed(spark, d):
        return measures.rank_methods(one(spark, d)).select("method", "l", F.col("place").cast("long").alias("place"))

    def stats(spark, d):
        a, _ = supp(spark, d)
        out = measures.repeat(workloads.cached(a), {"uniform": lambda s: baselines.uniform_select(a, 1, s)}, 1)
        return out.select("method", "l", F.round("avg_acc", 3).alias("avg_acc"), F.round("std_acc", 3).alias("std_acc"))

    def ratio(spark, d):
        """What one column leaves of a sign sketch over what it leaves of the matrix."""
        a, _ = supp(spark, d)
        b = sketch.publish(sketch.sketch_columns(a, 8, "sign", draws="hash"), a.m, 8)
        return spark.createDataFrame([(round(measures.sketch_error_ratio(a, greedy.greedy_select(a, 1), b, 1 / 8), 6),)], "ratio double")

    def distances(spark, d):
        a, _ = supp(spark, d)
        b = sketch.publish(sketch.sketch_columns(a, 8, "sign", draws="hash"), a.m, 8)
        rows = measures.distance_distortion(a, b, [(0, 1), (0, 5), (3, 7), (10, 20)], 1 / 8)
        return rows.select("i", "j", F.round("ratio", 6).alias("ratio"))

    def optimum(spark, d):
        a, _ = matrix.from_cells(workloads.brand_cells(spark, d))
        best, found = baselines.exhaustive_select(a, 2), greedy.greedy_select(a, 2)
        return spark.createDataFrame([(round(measures.optimum_ratio(a, found, 2), 6), measures.overlap(best, found))], "ratio double, both int")

    def coverage(spark, d):
        a = workloads.emb(spark, d)
        labels = load(spark, d, "embeddings", "vec_id", "label").withColumnRenamed("vec_id", "col_id")
        return measures.coverage_by(greedy.greedy_select(a, 10, "rowspace"), labels, "label")

    def growth(spark, d):
        """Share of the energy that l columns explain."""
        a, _ = supp(spark, d)
        return measures.growth(greedy.greedy_select(a, 8)).select("l", F.round("share", 6).alias("share"))

    greedy_one = oracle.greedy(MONTH, 1)
    pivot = "(SELECT p FROM g WHERE p = q ORDER BY v DESC, p LIMIT 1)"
    three = f"WITH s_ AS MATERIALIZED ({greedy_one}), {ctes}, {ends}, f AS (SELECT 'greedy' AS method, (SELECT key FROM s_) AS p UNION ALL SELECT 'pivoted_qr', {pivot} UNION ALL SELECT 'uniform', ({u(5)})), r AS (SELECT method, 1 AS l, {acc} AS rel_acc, err FROM f JOIN own USING (p), ref, low)"
    many = f"WITH {ctes}, {ends}, f AS (SELECT 'uniform' AS method, p FROM ({draws(range(10))})), r AS (SELECT method, 100 * (base - err) / (base - low) AS a FROM f JOIN own USING (p), ref, low) SELECT method, 1 AS l, round(avg(a), 3) AS avg_acc, round(stddev_samp(a), 3) AS std_acc FROM r GROUP BY method"
    sk = oracle.sketch("SELECT r, v, i FROM cells_", 8, "sign")
    ratio_sql = f"WITH s_ AS MATERIALIZED ({greedy_one}), cells_ AS MATERIALIZED ({SUPP}), sk_ AS MATERIALIZED ({sk}), x AS (SELECT r, v FROM cells_ WHERE c = (SELECT key FROM s_)), d AS (SELECT k, sum(sk_.v * x.v) AS v FROM sk_ JOIN x USING (r) GROUP BY k) SELECT round(((SELECT sum(v * v) FROM sk_) - (SELECT sum(v * v) FROM d) / (SELECT sum(v * v) FROM x)) / 8 / (SELECT residual_sq FROM s_), 6) AS ratio"
    rows = f"WITH cells_ AS MATERIALIZED ({SUPP}), sk_ AS MATERIALIZED ({sk}), n AS (SELECT r, dense_rank() OVER (ORDER BY r) - 1 AS row FROM (SELECT DISTINCT r FROM cells_)), want AS (SELECT * FROM (VALUES (0, 1), (0, 5), (3, 7), (10, 20)) t(i, j))"
    part = lambda table, key: f"(SELECT w.i, w.j, sum(pow(coalesce(x.v, 0) - coalesce(y.v, 0), 2)) AS d FROM want w JOIN n a ON a.row = w.i JOIN n b ON b.row = w.j CROSS JOIN (SELECT DISTINCT {key} AS kk FROM {table}) z LEFT JOIN {table} x ON x.r = a.r AND x.{key} = z.kk LEFT JOIN {table} y ON y.r = b.r AND y.{key} = z.kk GROUP BY ALL)"
    dist = f"{rows} SELECT i::INTEGER AS i, j::INTEGER AS j, round(s.d / 8 / a.d, 6) AS ratio FROM {part('sk_', 'k')} s JOIN {part('cells_', 'c')} a USING (i, j) WHERE a.d > 0"
    brand2 = oracle.greedy(oracle.BRAND, 2)
    gram = f"c AS MATERIALIZED ({oracle.BRAND}), g AS MATERIALIZED (SELECT a.c AS p, b.c AS q, sum(a.v * b.v) AS v FROM c a JOIN c b USING (r) GROUP BY ALL), h AS MATERIALIZED (SELECT a.p, b.p AS q, sum(a.v * b.v) AS v FROM g a JOIN g b USING (q) GROUP BY ALL)"
    best = f"WITH s_ AS MATERIALIZED ({brand2}), {gram}, pairs AS (SELECT x.p, x.q, (gq.v * hp.v - 2 * x.v * hx.v + gp.v * hq.v) / (gp.v * gq.v - x.v * x.v) AS gain FROM g x JOIN g gp ON gp.p = x.p AND gp.q = x.p JOIN g gq ON gq.p = x.q AND gq.q = x.q JOIN h hp ON hp.p = x.p AND hp.q = x.p JOIN h hq ON hq.p = x.q AND hq.q = x.q JOIN h hx ON hx.p = x.p AND hx.q = x.q WHERE x.p < x.q ORDER BY gain DESC LIMIT 1) SELECT round((SELECT sum(score) FROM s_) / gain, 6) AS ratio, (SELECT count(*) FROM s_ WHERE key IN (p, q))::INTEGER AS both FROM pairs"
    return {
        "relative_accuracy_l1": (f"{three} SELECT method, l, rel_acc FROM r", accuracy),
        "method_rank": (f"{three} SELECT method, l, dense_rank() OVER (ORDER BY err) AS place FROM r", placed),
        "repeat_stats": (many, stats),
        "sketch_error_ratio_supp": (ratio_sql, ratio),
        "row_distances": (dist, distances),
        "optimum_ratio_brand": (best, optimum),
        "coverage_by_label": (f"WITH s_ AS MATERIALIZED ({oracle.greedy_rows(oracle.EMB, 10)}) SELECT label, count(*) AS n, count(key) AS chosen FROM embeddings LEFT JOIN s_ ON key = vec_id GROUP BY label", coverage),
        "growth_with_l": (f"WITH s_ AS MATERIALIZED ({oracle.greedy(MONTH, 8)}) SELECT step AS l, round(1 - residual_sq / (SELECT sum(v * v) FROM ({MONTH})), 6) AS share FROM s_", growth),
    }


# Uses of a selection


def _uses() -> dict:
    def shown(spark, d):
        """The chosen suppliers by name, with the line items that they stand for."""
        a, names = supp(spark, d)
        s = greedy.greedy_select(a, 5).join(F.broadcast(names), "col_id")
        people = load(spark, d, "supplier", "s_suppkey", "s_name")
        items = load(spark, d, "lineitem", "l_suppkey").groupBy("l_suppkey").agg(F.count("*").alias("items"))
        rows = s.join(people, F.col("key") == F.col("s_suppkey")).join(items, F.col("key") == F.col("l_suppkey"))
        return rows.select("step", "s_name", "items", F.round("score", 3).alias("score"))

    def grouped(spark, d):
        """Three representative embeddings of each label, by the table function in SQL."""
        udfs.register(spark)
        rows = load(spark, d, "embeddings", "vec_id", "embedding", "label")
        rows.select(F.col("vec_id").alias("col_id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"), "label").createOrReplaceTempView("labelled_vectors")
        chosen = spark.sql("SELECT * FROM select_columns(TABLE(labelled_vectors) PARTITION BY (label), 3)")
        labels = rows.select(F.col("vec_id").alias("col_id"), "label")
        return chosen.join(labels, "col_id").select("label", "step", "col_id", F.round("score", 3).alias("score"))

    def local(spark, d):
        """The same by a grouped kernel, for suppliers of each nation."""
        cells = workloads.month_cells(spark, d, "l_suppkey")
        a, names = matrix.from_cells(cells)
        nation = load(spark, d, "supplier", "s_suppkey", "s_nationkey")
        rows = a.df.join(names, "col_id").join(nation, F.col("key") == F.col("s_suppkey"))
        out = greedy.select_per_group(rows.select(F.col("s_nationkey").cast("long").alias("grp"), "col_id", "vec"), 2)
        return out.join(F.broadcast(names), "col_id").select(F.col("grp").alias("nation"), "step", "key", F.round("score", 3).alias("score"))

    one = " UNION ALL ".join(f"SELECT {g} AS label, step, key AS col_id, score FROM ({oracle.greedy(f'SELECT c, r, v FROM cells_ WHERE label = {g}', 3)})" for g in range(10))
    emb = oracle.EMB.replace("vec_id AS c,", "vec_id AS c, label,")
    nations = " UNION ALL ".join(f"SELECT {g}::BIGINT AS nation, step, key, score FROM ({oracle.greedy(f'SELECT r, c, v FROM cells_ WHERE s_nationkey = {g}', 2)})" for g in range(25))
    return {
        "w16_use_of_output": (f"WITH s_ AS ({oracle.greedy(MONTH, 5)}) SELECT step, s_name, items, score FROM s_ JOIN supplier ON key = s_suppkey JOIN (SELECT l_suppkey, count(*) AS items FROM lineitem GROUP BY 1) ON key = l_suppkey", shown),
        "select_per_group": (f"WITH cells_ AS MATERIALIZED ({emb}) {one}", grouped),
        "w18_per_nation": (f"WITH cells_ AS MATERIALIZED (SELECT x.*, s_nationkey FROM ({MONTH}) x JOIN supplier ON c = s_suppkey) {nations}", local),
    }


__all__ = ["register", "steps", "supp"]
