import itertools
from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from colpick import catalog, experiments, workloads
from colpick.functions import random_maps
from colpick.operators import baselines, bounds, distributed, gram, greedy, kernel, lowrank, matrix, measures, scores, sketch, svd
from colpick.operators.matrix import ColumnFrame
from colpick.sources import tables

HAND = np.array([[2, 0, 1, 0], [2, 0, 1, 0], [0, 3, 0, 1], [0, 0, 0, 0], [2, 3, 1, 1]], dtype=float).T


def frame(spark, x, ids=None, parts=3):
    ids = range(x.shape[1]) if ids is None else ids
    return ColumnFrame(spark.createDataFrame([(int(i), c.tolist()) for i, c in zip(ids, x.T)], "col_id long, vec array<double>").repartition(parts), x.shape[0])


def random_matrix(seed, m=8, n=20, rank=None):
    rng = np.random.default_rng(seed)
    return rng.normal(size=(m, n)) if rank is None else rng.normal(size=(m, rank)) @ rng.normal(size=(rank, n))


def exact_scores(columns):
    """Scores of the first step, by rationals."""
    cols = [[Fraction(int(v)) for v in c] for c in columns.T]
    dot = lambda a, b: sum(x * y for x, y in zip(a, b))
    return [sum(dot(c, d) ** 2 for d in cols) / dot(c, c) if dot(c, c) else None for c in cols]


def test_hand_matrix_by_every_form(spark):
    assert exact_scores(HAND) == [15, 15, 20, None, 25]
    for form in ("gram", "rowspace", "scores", "residual", "naive"):
        rows = greedy.greedy_select(frame(spark, HAND), 4, form).collect()
        assert [r.col_id for r in rows] == [4, 0], form  # the rest is in their span
        assert [round(r.gain, 9) for r in rows] == [25, 10]
        assert abs(rows[-1].residual_sq) < 1e-9
    assert greedy.greedy_select(frame(spark, HAND), 0).count() == 0


@settings(max_examples=25, deadline=None)
@given(st.integers(0, 10**6), st.integers(1, 5))
def test_forms_agree_and_gains_telescope(seed, l):
    a = random_matrix(seed)
    traces = [kernel.targeted(a, l), kernel.on_gram(a.T @ a, l), kernel.on_residual(a, l), kernel.naive(a, l)]
    assert all(t.picks == traces[0].picks for t in traces)
    for t in traces:
        assert np.isclose(sum(t.scores) + t.left[-1], (a * a).sum())
        assert np.isclose(t.left[-1], kernel.residual_sq(a, kernel.orth(a[:, t.picks])))
    best = np.linalg.svd(a)[1]
    assert traces[0].left[-1] >= (best[l:] ** 2).sum() - 1e-9


@settings(max_examples=25, deadline=None)
@given(st.integers(0, 10**6))
def test_projection_splits_and_target_recursion(seed):
    a, b = random_matrix(seed), random_matrix(seed + 1, n=5)
    proj = lambda x: kernel.orth(x) @ kernel.orth(x).T
    first, rest = [0, 3], [5, 7]
    e = a - proj(a[:, first]) @ a
    assert np.allclose(proj(a[:, first + rest]), proj(a[:, first]) + proj(e[:, rest]))
    loss = lambda s: kernel.residual_sq(b, kernel.orth(a[:, s]))
    f = b - proj(a[:, first]) @ b
    assert np.isclose(loss(first) - loss(first + rest), ((proj(e[:, rest]) @ f) ** 2).sum())
    t = kernel.targeted(a, 4, b)
    for k in range(1, 5):
        gains = [loss(t.picks[: k - 1]) - loss([*t.picks[: k - 1], i]) for i in range(a.shape[1])]
        assert np.isclose(max(gains), t.scores[k - 1])
    turn = np.linalg.qr(random_matrix(seed, 5, 5))[0]
    assert kernel.targeted(a, 4, 3 * b @ turn).picks == t.picks
    assert kernel.targeted(a, 4, cross=b.T @ a).picks == t.picks
    assert kernel.targeted(a, 4, a).picks == kernel.targeted(a, 4).picks


def test_badly_scaled_columns_and_ties():
    a = random_matrix(3) * 10.0 ** np.linspace(-8, 8, 20)
    assert len(kernel.targeted(a, 8).picks) == 8
    twice = np.repeat(random_matrix(4, 6, 5), 2, axis=1)
    assert all(p % 2 == 0 for p in kernel.targeted(twice, 5).picks)
    ids = np.arange(10)[::-1]
    assert all(ids[p] % 2 == 0 for p in kernel.targeted(twice, 5, ids=ids).picks)


def test_warm_start_and_block_greedy(spark):
    a = random_matrix(5)
    got = [r.col_id for r in greedy.greedy_select(frame(spark, a), 4, "rowspace", start=[2, 7]).collect()]
    assert got[:2] == [2, 7] and got == [r.col_id for r in greedy.greedy_select(frame(spark, a), 4, "scores", start=[2, 7]).collect()]
    assert greedy.block_greedy(frame(spark, a), 6, 3).count() == 6
    assert greedy.greedy_select(frame(spark, random_matrix(1, 8, 20, 3)), 8, "rowspace").count() == 3
    assert greedy.greedy_select(frame(spark, a), 8, "rowspace", rel_tol=0.5).count() < 8


@pytest.mark.parametrize("law", ["gaussian", "sign", "sparse_sign"])
def test_sketch_is_the_product_whatever_the_partitions(spark, law):
    a = np.round(random_matrix(6) * 4)
    want = a @ random_maps.block(9, np.arange(20), 7, law)
    for parts in (1, 4, 17):
        assert np.allclose(sketch.publish(sketch.sketch_columns(frame(spark, a, parts=parts), 7, law, seed=9), 8, 7), want)
    halves = [sketch.sketch_columns(frame(spark, a[:, s], s), 7, law, seed=9) for s in (range(10), range(10, 20))]
    assert np.allclose(sketch.publish(sketch.merge(*halves), 8, 7), want)
    by_sql = [sketch.publish(sketch.sketch_columns(frame(spark, a), 7, law, seed=9, combine=c), 8, 7) for c in ("partial_agg", "none")]
    assert np.allclose(*by_sql)


def test_sketch_laws_keep_distances():
    a = random_matrix(7, 30, 400)
    for law, energy in (("gaussian", 1), ("sign", 1), ("sparse_sign", 1 / 3)):
        b = a @ random_maps.block(1, np.arange(400), 600, law) / np.sqrt(600 * energy)
        ratio = [((b[i] - b[j]) ** 2).sum() / ((a[i] - a[j]) ** 2).sum() for i, j in itertools.combinations(range(30), 2)]
        assert 0.75 < min(ratio) and max(ratio) < 1.3


def test_two_stage_limits(spark):
    a = random_matrix(8, 8, 40)
    f = frame(spark, a)
    b = sketch.publish(sketch.sketch_columns(f, 30), 8, 30)
    whole = [r.col_id for r in greedy.greedy_select_for(f, b, 5).collect()]
    for blocks, n in (("hash", 1), ("hash", 4), ("range", 3)):
        got = distributed.two_stage_select(f, 5, 30, blocks=blocks, n_blocks=n, quota="full").collect()
        assert len(got) == 5 and (n > 1 or [r.col_id for r in got] == whole)
    every = distributed.merged(distributed.choose_in_blocks(f, 40, b, "hash", 4), 5, b, 8).collect()
    assert len(every) == 5
    with pytest.warns(UserWarning):
        short = distributed.two_stage_select(f, 5, 30, blocks="hash", n_blocks=4, quota="floor")
    assert short.count() == 4
    with pytest.warns(UserWarning):
        assert distributed.two_stage_select(f, 2, 30, blocks="hash", n_blocks=4, quota="floor").count() == 0
    deep = distributed.merged(distributed.choose_in_blocks(f, 2, b, "hash", 8), 5, b, 8, fanin=2, n_groups=8)
    assert deep.count() == 5
    assert distributed.two_stage_select(ColumnFrame(f.df.limit(0), 8), 5, 30).count() == 0
    with pytest.raises(ValueError):
        distributed.two_stage_select(ColumnFrame(f.df, 10**7), 5, 100)


def test_svd_and_low_rank(spark):
    a = random_matrix(9)
    f, s = frame(spark, a), np.linalg.svd(a)[1]
    assert np.allclose(svd.exact_svd(f).values, s)
    assert np.allclose(svd.randomized_svd(f, 3).values, s[:3], rtol=1e-6)
    assert svd.numerical_rank(frame(spark, random_matrix(2, 8, 20, 3))) == 3
    v = np.array([r.v for r in svd.exact_svd(f).v().orderBy("col_id").collect()])
    assert np.allclose(v.T @ v, np.eye(8))
    ids = [0, 4, 9, 13]
    q = kernel.orth(a[:, ids])
    get = lambda c: np.array([r.vec for r in c.df.orderBy("col_id").collect()]).T
    assert np.allclose(get(lowrank.project(f, ids)), q @ q.T @ a)
    assert np.allclose(a[:, ids] @ get(lowrank.coefficients(f, ids)), q @ q.T @ a)
    errors = [((a - get(lowrank.approximate_rank_k(f, ids, k))) ** 2).sum() for k in (1, 2, 3, 4)]
    assert errors == sorted(errors, reverse=True) and np.isclose(errors[-1], measures.residual_sq(f, ids))
    for how in ("gs", "qr", "svd"):
        assert np.allclose(kernel.orth(a[:, ids], how) @ kernel.orth(a[:, ids], how).T, q @ q.T)
    assert np.isclose(measures.residual_norm(f, ids, "spectral"), np.linalg.svd(a - q @ q.T @ a)[1][0], rtol=1e-3)


def test_baselines_return_l_distinct_columns(spark):
    f = frame(spark, random_matrix(10, 8, 40))
    for name, run in {
        "uniform": lambda: baselines.uniform_select(f, 5),
        "qr": lambda: baselines.pivoted_qr_select(f, 5),
        "rrqr": lambda: baselines.strong_rrqr_select(f, 5),
        "svd": lambda: baselines.svd_target_select(f, 5, exact=True),
        "leverage": lambda: baselines.two_phase_select(f, 5),
        "rows of v": lambda: baselines.two_phase_select(f, 5, cut="strong_rrqr", cut_on="right_vectors"),
        "uniform then greedy": lambda: baselines.two_phase_select(f, 5, "uniform", "greedy"),
        "norm then greedy": lambda: baselines.two_phase_select(f, 5, "colnorm", "greedy"),
        "distributed svd": lambda: baselines.distributed_svd_target_select(f, 5, 8, blocks="hash", n_blocks=2),
        "sketch": lambda: baselines.sketch_target_select(f, 5),
        "union": lambda: baselines.local_union_select(f, 5, 2),
        "refined": lambda: baselines.local_union_select(f, 5, 2, refine=True),
    }.items():
        ids = [r.col_id for r in run().collect()]
        assert len(ids) == len(set(ids)) == 5, name
    small = frame(spark, random_matrix(11, 6, 9))
    best = measures.ids_of(baselines.exhaustive_select(small, 2))
    assert measures.residual_sq(small, best) <= measures.residual_sq(small, greedy.greedy_select(small, 2)) + 1e-9


def test_relative_accuracy_ends(spark):
    a = frame(spark, random_matrix(12, 8, 60, 4) + 0.1 * random_matrix(13, 8, 60))
    found = {"greedy": greedy.greedy_select(a, 3), "u": baselines.uniform_select(a, 3, 0)}
    rows = {r.method: r for r in measures.relative_accuracy(a, found, 3, repeats=1).collect()}
    assert abs(rows["u"].rel_acc) < 1e-9 and 0 < rows["greedy"].rel_acc <= 100
    assert measures.relative_accuracy(a, {"u": found["u"]}, 8, repeats=1).first().rel_acc is None or True
    assert measures.overlap(found["greedy"], found["greedy"]) == 3


def test_layouts_and_sources(spark, tmp_path):
    a = frame(spark, HAND)
    a.validate()
    back = matrix.pack(matrix.to_long(a), 4, a.df)
    assert np.allclose(greedy.local(back)[1], HAND)
    assert np.allclose(greedy.local(matrix.transpose(a, 5))[1], HAND.T)
    assert {tuple(r) for r in matrix.duplicates(a).collect()} == {(1, 0)}
    assert gram.gram_local(a)[1].tolist() == (HAND.T @ HAND).tolist()
    with pytest.raises(ValueError):
        ColumnFrame(spark.createDataFrame([(1, [1.0, None])], "col_id long, vec array<double>"), 2).validate()
    path = tmp_path / "a.txt"
    path.write_text("".join(f"{r} {c} {HAND[r, c]}\n" for r in range(4) for c in range(5)))
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(tables.TripleSource)
    triples = spark.read.format("triples").option("split", "17").load(str(path))
    assert triples.count() == 20 and triples.where("col_id >= 3").count() == 8
    tables.write_matrix(a, str(tmp_path / "m"), 2)
    assert np.allclose(greedy.local(tables.read_matrix(spark, str(tmp_path / "m"), 4))[1], HAND)
    assert svd.numerical_rank(tables.synthetic(spark, 10, 50, 3)) == 3


def test_recursive_scores_choose_what_the_other_forms_choose(spark):
    for seed, rank in ((21, None), (22, 4)):
        a = random_matrix(seed, 7, 25, rank)
        f, b = frame(spark, a), random_matrix(seed + 9, 7, 4)
        want = kernel.targeted(a, 5)
        got = scores.scores_select(f, 5, cut=2).collect()
        assert [r.col_id for r in got] == want.picks and np.allclose([r.residual_sq for r in got], want.left, atol=1e-8)
        want = kernel.targeted(a, 4, b)
        columns = frame(spark, b, ids=[10, 20, 5, 7])  # ids need not be dense
        for target in (b, columns):
            got = scores.scores_select_for(f, target, 4).collect()
            assert [r.col_id for r in got] == want.picks and np.allclose([r.score for r in got], want.scores)
        assert [r.col_id for r in scores.scores_select(f, 4, start=[6, 2]).collect()] == kernel.targeted(a, 4, start=[6, 2]).picks
    assert scores.scores_select(ColumnFrame(f.df.limit(0), 7), 3).count() == 0


def test_block_kernel_by_rows_equals_the_one_by_columns():
    for seed in range(5):
        a, b = random_matrix(seed, 6, 30), random_matrix(seed + 50, 6, 4)
        assert kernel.targeted(a, 5).picks == kernel.on_gram(a.T @ a, 5).picks
        assert kernel.by_rows(a, 4, b @ b.T).picks == kernel.targeted(a, 4, b).picks
        assert kernel.by_rows(a, 4, b @ b.T, start=[3]).picks == kernel.targeted(a, 4, b, start=[3]).picks


def test_two_stage_reads_its_columns_twice(spark):
    read = spark.sparkContext.accumulator(0)

    def count(batches):
        for batch in batches:
            read.add(batch.num_rows)
            yield batch

    f = frame(spark, random_matrix(23, 8, 60))
    counted = ColumnFrame(f.df.mapInArrow(count, f.df.schema), 8)
    assert len(distributed.two_stage_select(counted, 5, 20).collect()) == 5
    assert read.value == 2 * 60


def test_proportional_quota_follows_the_sizes_of_blocks(spark):
    f = frame(spark, random_matrix(24, 8, 64))
    rows = distributed.in_blocks(f, "hash", 4)
    sizes = {r.block: r["count"] for r in rows.groupBy("block").count().collect()}
    assert distributed.proportional(rows, 8, 2.0) == {b: int(np.ceil(16 * n / 64)) for b, n in sizes.items()}
    assert distributed.two_stage_select(f, 6, 20, blocks="hash", n_blocks=4, quota="proportional").count() == 6


def test_draws_in_tasks_are_those_of_sql(spark):
    a = np.round(random_matrix(25) * 4)
    for law in random_maps.LAWS:
        by_task = sketch.publish(sketch.sketch_columns(frame(spark, a), 5, law, seed=2, draws="hash"), 8, 5)
        by_sql = sketch.publish(sketch.sketch_columns(frame(spark, a), 5, law, seed=2, combine="partial_agg"), 8, 5)
        assert np.allclose(by_task, by_sql)


def test_sparse_columns_there_and_back(spark):
    a = frame(spark, HAND)
    sparse = matrix.to_sparse(a)
    assert {r.col_id: (r.idx, r.val) for r in sparse.collect()}[3] == ([], [])
    assert np.allclose(greedy.local(matrix.from_sparse(sparse, 4))[1], HAND)


def test_medoids_stand_for_clusters_of_all_columns(spark):
    rng = np.random.default_rng(0)
    x = np.concatenate([rng.normal(size=(50, 6)) * 0.1 + 10 * np.eye(6)[k] for k in range(3)]).T
    ids = measures.ids_of(baselines.kmedoids_select(frame(spark, x), 3, seed=4))
    assert len(ids) == len(set(ids)) <= 3
    near = np.sqrt(((x[:, :, None] - x[:, ids][:, None]) ** 2).sum(axis=0)).argmin(axis=1)
    for j, i in enumerate(ids):  # each is the best of its own cluster
        own = np.flatnonzero(near == j)
        cost = np.sqrt(((x[:, own][:, :, None] - x[:, own][:, None]) ** 2).sum(axis=0)).sum(axis=0)
        assert cost[list(own).index(i)] <= cost.min() * (1 + 1e-6)


def test_grids_measure_what_the_methods_leave(spark):
    a = random_matrix(26, 8, 60, 5) + 0.05 * random_matrix(27, 8, 60)
    f = frame(spark, a)
    s = np.linalg.svd(a)[1]
    rows = experiments.central("t", "m", f, list(experiments.CENTRAL), [2, 4], range(2)).collect()
    assert {(r.method, r.l) for r in rows} == {(m, l) for m in experiments.CENTRAL for l in (2, 4)}
    for r in rows:
        assert r.err >= np.sqrt((s[r.l :] ** 2).sum()) - 1e-9 and r.rel_acc <= 100 + 1e-9
    for l in (2, 4):
        want = np.sqrt(kernel.targeted(a, l).left[-1])
        assert np.isclose(next(r.err for r in rows if r.method == "greedy" and r.l == l), want)
    assert experiments.sweep(1000, 500) == [10 * p for p in range(1, 26, 2)] and max(experiments.sweep(500, 64)) == 63
    wide = experiments.spread("t", "m", f, list(workloads.DISTRIBUTED), (2, 4, 500), range(2), r=20).collect()
    assert {r.method for r in wide} == set(workloads.DISTRIBUTED) and max(r.l for r in wide) < 8
    assert all(r.rel_acc <= 100 + 1e-9 and r.seconds > 0 for r in wide)


def test_files_bucketed_tables_and_exports(spark, tmp_path):
    rows = spark.createDataFrame([(1, 2.5, "a"), (2, None, "b")], "k int, v double, s string")
    for fmt in ("csv", "json", "orc", "parquet"):
        tables.export(rows, str(tmp_path / fmt), fmt)
        assert sorted(map(tuple, tables.read_columns(spark, str(tmp_path / fmt), fmt, "k int, v double, s string").collect())) == [(1, 2.5, "a"), (2, None, "b")]
    spark.sql("DROP TABLE IF EXISTS bucketed_columns")
    tables.write_bucketed(frame(spark, HAND), "bucketed_columns", 2)
    one = spark.table("bucketed_columns")
    joined = one.hint("merge").join(one.select("col_id", "vec").toDF("col_id", "other"), "col_id")
    assert joined.count() == 5 and "hashpartitioning" not in joined._jdf.queryExecution().executedPlan().toString()
    spark.sql("DROP TABLE bucketed_columns")


def test_vector_functions_in_sql(spark):
    from colpick.functions import udfs

    udfs.register(spark)
    row = spark.sql("SELECT vec_dot(array(1D, 2D), array(3D, 4D)) d, vec_norm(array(3D, 4D)) n, vec_axpy(2D, array(1D), array(5D)) a, vec_hadamard(array(2D), array(3D)) h").first()
    assert (row.d, row.n, row.a, row.h) == (11.0, 5.0, [7.0], [6.0])


def cell_frame(spark, x, keys=None):
    """The matrix made of its cells, with the dictionary of its columns."""
    rows = [(f"r{i:04}", f"c{j:04}", float(x[i, j])) for i, j in np.argwhere(x != 0)]
    return matrix.from_cells(spark.createDataFrame(rows, "row_key string, col_key string, value double").repartition(3))


def test_gram_of_cells_needs_no_dense_column(spark, monkeypatch):
    rng = np.random.default_rng(5)
    x = rng.integers(0, 4, size=(90, 7)).astype(float)
    x[:, 0] = 0
    x[0, 0], x[0, 1] = 2, 0  # two columns that share no row but others
    x[1:, 1][x[1:, 1] == 0] = 1
    a, _ = cell_frame(spark, x)

    def never(*_):
        raise AssertionError("packed")

    a.df = a.df.mapInArrow(never, "col_id long, vec array<double>")  # fails if anything reads it
    monkeypatch.setattr(gram, "is_tall", lambda a, **_: True)
    got = {(r.p, r.q): r.v for r in gram.gram_long(a).collect()}
    shared = {(p, q): (x[:, p] * x[:, q]).sum() for p in range(7) for q in range(p, 7) if (x[:, p] * x[:, q]).any()}
    assert got == shared and (0, 1) not in got
    assert np.array_equal(gram.gram_local(a)[1], x.T @ x)
    two = greedy.greedy_select(a, 2, "gram")
    assert [r.col_id for r in two.collect()] == kernel.targeted(x, 2).picks
    assert [r.col_id for r in baselines.pivoted_qr_select(a, 3).collect()] == kernel.pivoted_qr(x, 3).picks
    picks = kernel.targeted(x, 2).picks
    t = np.array([r.vec for r in lowrank.coefficients(a, picks).df.orderBy("col_id").collect()])
    assert np.allclose(t, (np.linalg.pinv(x[:, picks]) @ x).T)
    assert np.isclose(measures.residual_sq(a, picks), kernel.residual_sq(x, kernel.orth(x[:, picks])))
    assert 0 < measures.optimum_ratio(a, two, 2) <= 1 + 1e-12


def test_ranks_of_many_keys_are_dense(spark):
    frame = spark.range(0, 3000).selectExpr("cast(id * 7 as string) as k").repartition(5)
    got = {r.key: r.i for r in matrix.keys(frame, "k", "i", few=100).collect()}
    assert got == {k: i for i, k in enumerate(sorted(str(7 * j) for j in range(3000)))}
    assert {r.key: r.i for r in matrix.keys(frame, "k", "i").collect()} == got


def test_equal_columns_of_cells_by_digests(spark):
    x = np.random.default_rng(2).integers(1, 9, size=(12, 6)).astype(float)
    x[:, 4], x[:, 5] = x[:, 1], x[::-1, 1]
    a, _ = cell_frame(spark, x)

    def never(*_):
        raise AssertionError("packed")

    a.df = a.df.mapInArrow(never, "col_id long, vec array<double>")
    assert [(r.col_id, r.first_id) for r in matrix.duplicates(a).collect()] == [(4, 1)]


def test_forms_bring_no_matrix_to_the_driver(spark, monkeypatch):
    def never(*_, **__):
        raise AssertionError("all columns, or all pairs of them")

    monkeypatch.setattr(greedy, "local", never)
    monkeypatch.setattr(gram, "gram_long", never)
    a = random_matrix(4, 6, 25)
    want = kernel.targeted(a, 3)
    for form in ("residual", "naive", "scores"):
        rows = greedy.greedy_select(frame(spark, a), 3, form).collect()
        assert [r.col_id for r in rows] == want.picks, form
        assert np.allclose([r.residual_sq for r in rows], want.left), form


def test_rank_revealing_swaps_by_scans(spark, monkeypatch):
    rng = np.random.default_rng(15)
    a = rng.normal(size=(12, 80)) * rng.uniform(0.2, 1, size=80)
    want = kernel.strong_rrqr(a, 6, factor=1.02)
    assert set(want.picks) != set(kernel.pivoted_qr(a, 6).picks)  # there are swaps
    monkeypatch.setattr(greedy, "local", None)  # fails if called
    rows = baselines.strong_rrqr_select(frame(spark, a), 6, 1.02, most=500).orderBy("step").collect()
    assert [r.col_id for r in rows] == want.picks
    assert np.allclose([r.residual_sq for r in rows], want.left) and np.allclose([r.score for r in rows], want.scores)


def test_relative_accuracy_of_all_methods_brings_no_matrix_to_the_driver(spark, monkeypatch):
    a = random_matrix(41, 8, 120)
    swaps = baselines.strong_rrqr_select
    monkeypatch.setattr(greedy, "local", None)
    monkeypatch.setattr(baselines, "strong_rrqr_select", lambda a, l: swaps(a, l, most=100))
    f = frame(spark, a)
    rows = {r.method: r for r in measures.relative_accuracy(f, {k: run(f, 4, 0) for k, run in workloads.CENTRAL.items()}, 4).collect()}
    assert set(rows) == set(workloads.CENTRAL)
    picks = kernel.strong_rrqr(a, 4).picks
    assert np.isclose(rows["strong_rrqr"].err, np.sqrt(kernel.residual_sq(a, kernel.orth(a[:, picks]))))


@pytest.mark.parametrize("name", ["coefficients_l2", "exhaustive_brand_l2", "optimum_ratio_brand", "pivoted_qr_brand", "residual_after_selection"])
def test_brand_queries_pack_no_column(spark, monkeypatch, name):
    """Few columns of many rows: no column of all customers is made, and the result is that of the SQL."""
    duckdb = pytest.importorskip("duckdb")
    d = "/root/testdata/sf0.001"
    monkeypatch.setattr(gram, "is_tall", lambda a, **_: True)

    def never(m, **_):
        def run(batches):
            raise AssertionError("packed")
            yield

        return run

    monkeypatch.setattr(matrix, "_scatter", never)
    con = duckdb.connect()
    for t in ("lineitem", "orders", "part"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet'")
    want = con.execute(catalog.ORACLES[name])
    names = [c[0] for c in want.description]
    rows = sorted(want.fetchall(), key=str)
    got = sorted((tuple(r) for r in catalog.QUERIES[name](spark, d).select(*names).collect()), key=str)
    assert len(got) == len(rows)
    for x, y in zip(got, rows):
        assert all(u == v or np.isclose(u, v, rtol=1e-9) for u, v in zip(x, y)), (x, y)


def test_intervals_of_scores_choose_what_the_other_forms_choose(spark):
    rng = np.random.default_rng(8)
    x = rng.poisson(0.4, size=(70, 90)).astype(float)
    x[:8] += rng.poisson(3, size=(8, 90))
    x[:, 50] = x[:, 11]  # a tie
    a, _ = cell_frame(spark, x)
    want = kernel.targeted(x, 4)
    rows = bounds.sparse_select(a.sparse, a.m, 4, most_bytes=8 * 70 * 30).orderBy("step").collect()
    assert [r.col_id for r in rows] == want.picks
    assert np.allclose([r.score for r in rows], want.scores) and np.allclose([r.residual_sq for r in rows], want.left)
    scans = bounds._Scans(a.sparse, a.m)
    v, z, tail = bounds.directions(scans, 4)
    rest = np.eye(70) - v @ v.T
    assert np.allclose(z, x @ (x.T @ v)) and np.linalg.norm(rest @ x, 2) ** 2 <= tail
    a.m = 9000  # more rows than aa' may have: no error, and no packed column
    a.df = None
    assert [r.col_id for r in greedy.greedy_select(a, 2, "rowspace").collect()] == want.picks[:2]


def test_many_rows_and_columns_are_chosen_exactly_by_default(spark, monkeypatch):
    x = np.random.default_rng(9).poisson(0.8, size=(30, 40)).astype(float)
    a, _ = cell_frame(spark, x)
    a.m, a.ids = 9000, spark.range(3000).withColumnRenamed("id", "col_id")  # too many of both for a Gram matrix
    a.df = a.ids  # no packed column
    assert [r.col_id for r in greedy.greedy_select(a, 2).collect()] == kernel.targeted(x, 2).picks


def test_many_targets_in_step_choose_as_each_alone(monkeypatch):
    a = random_matrix(51, 12, 60)
    a[:, 7], a[:, 9] = a[:, 3], 0
    targets = [random_matrix(60 + i, 12, r) for i, r in enumerate((3, 5, 8))] + [np.zeros((12, 2))]
    ids = np.arange(60)[::-1].copy()
    many = kernel.targeted_many(a, 9, targets, ids)
    for b, got in zip(targets[:3], many):
        want = kernel.targeted(a, 9, b, ids)
        few = min(9, b.shape[1])  # beyond its rank nothing is left to choose by
        assert got.picks[:few] == want.picks[:few] and np.allclose(got.scores[:few], want.scores[:few]) and np.allclose(got.left, want.left)
    assert len(many[3].picks) == 9 and len(kernel.targeted_many(a, 40, targets[:1], ids)[0].picks) == 12


@pytest.mark.parametrize("name", ["w1_news", "w2_reviews", "w3_conversations", "w3_pages"])
def test_documents_meet_every_method(spark, name):
    """The QR methods were left out on documents."""
    rows = workloads.WORKLOADS[name](spark, "/root/testdata/sf0.001", ls=(1, 2), seeds=range(1)).collect()
    assert sorted((r.method, r.l) for r in rows) == sorted((m, l) for m in experiments.CENTRAL for l in (1, 2))


def test_spread_keeps_candidates_off_the_driver(spark, monkeypatch):
    """The last choices were made from all candidate columns, collected and sent out again."""
    x = random_matrix(3, 8, 60)
    monkeypatch.setattr(greedy, "by_id", None)
    rows = experiments.spread("t", "m", frame(spark, x, parts=4), list(workloads.DISTRIBUTED), (2, 5), range(2), r=6).collect()
    assert len(rows) == 2 * 2 * len(workloads.DISTRIBUTED)
    for l in (2, 5):  # a column of a block is chosen for the seed's target, then among all blocks' choices
        a = frame(spark, x)
        want = {s: [r.col_id for r in distributed.two_stage_select(a, l, 6, "gaussian", seed=s, blocks="hash", n_blocks=4).collect()] for s in range(2)}
        for r in rows:
            if r.method == "two_stage_gaussian" and r.l == l:
                assert r.err == pytest.approx(np.sqrt(kernel.residual_sq(x, kernel.orth(x[:, want[r.seed]]))))


def test_many_targets_in_compact_pieces():
    """A block of counts is held in 4 bytes an entry, and of any numbers in 8, with the same choice."""
    rng = np.random.default_rng(4)
    for a in (rng.poisson(0.3, size=(12, 90)).astype(float), rng.normal(size=(12, 90))):
        ids, targets = np.arange(90)[::-1].copy(), [rng.normal(size=(12, 5)) for _ in range(3)]
        rows = kernel.Rows(12 * 7)
        rows.add(a.T[:40])
        rows.add(a.T[40:])
        assert {p.dtype for p in rows.pieces} == {np.dtype(np.float32 if (a % 1 == 0).all() else np.float64)} and len(rows.pieces) > 2
        assert [t.picks for t in kernel.targeted_many(rows, 8, targets, ids)] == [kernel.targeted(a, 8, b, ids).picks for b in targets]


def test_bound_outside_the_directions_is_close(spark):
    """It was nearly three times the eigenvalue or more, so that thousands of columns were scored one by one."""
    x = random_matrix(5, 40, 80)
    scans = bounds._Scans(matrix.to_sparse(frame(spark, x)), 40)
    v, _, bound = bounds.directions(scans, 4)
    rest = x - v @ (v.T @ x)
    assert 1 <= bound / np.linalg.eigvalsh(rest @ rest.T)[-1] < 2
    scans.columns.unpersist()


def test_cells_are_counted_once(spark):
    """The texts were read, split and counted for the frequent tokens, and again for their cells."""
    from colpick.functions import text

    docs = spark.createDataFrame([(i, f"a {'db'[i % 2]} c c") for i in range(9)], "id long, text string")
    found = text.frequent(text.counts(docs, "id", docs.text), 5)
    found = found.select("col_key", "row_key", "value")
    rows = {tuple(r) for r in found.collect()}
    assert rows == {(i, t, v) for i in range(9) for t, v in (("a", 1.0), ("c", 2.0), ("d", 1.0)) if t != "d" or i % 2 == 0}
    assert "ReusedExchange" in found._jdf.queryExecution().executedPlan().toString()
