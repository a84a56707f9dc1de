"""Invariants and brute-force checks of the method and its parts."""

import math
from dataclasses import replace

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from subvote.functions import bounds
from subvote.functions import vectors as V
from subvote.operators import activation, candidates, cells, codebooks, engine, exact, graph, learned_pq, metrics, onebit_ivf, refine, rotation, spectral
from subvote.operators.arrow import sign_words
from subvote.operators.engine import IndexParams, SearchParams, append, build_index, choose, counters, filtered_knn, footprint, load_index, save_index, search, search_relational
from subvote.operators.subspaces import uniform_layout, variance_layout
from subvote.sources import vectors as sources

PARAMS = IndexParams(m=8, k=8, init="id_stride", iters=0, policy="never", shard_rows=100, storage="f8", train_rows=None)


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.fixture(scope="module")
def e64(spark, sf):
    base, queries = sources.split(sources.embeddings(spark, sf))
    return base.cache(), queries.cache()


@pytest.fixture(scope="module")
def truth(e64):
    return exact.knn_relational(*e64, 10).cache()


def test_bulk_and_relational_exact_agree(e64, truth):
    assert rows(exact.knn(*e64, 10)) == rows(truth)


def test_all_cells_open_is_exact(e64, truth):
    index = build_index(e64[0], PARAMS)
    assert rows(search(index, e64[1], 10, SearchParams("guaranteed", 1.0, 1.0))) == rows(truth)


@pytest.mark.parametrize("shard_rows", [30, 120, 10_000])
def test_shards_do_not_change_guaranteed_results(spark, e64, shard_rows):
    base, queries = e64
    layout = uniform_layout(64, 8)
    params = SearchParams("guaranteed", 0.2, 0.4)
    plan = search_relational(base, queries, layout, codebooks.stride_codebook(base, layout, 8), 8, base.count(), 10, params)
    index = build_index(base.repartition(5), replace(PARAMS, shard_rows=shard_rows))
    assert rows(search(index, queries, 10, params)) == rows(plan)


def test_fallback_takes_the_best_scores(e64):
    base, queries = e64
    layout = uniform_layout(64, 8)
    params = SearchParams("guaranteed", 0.05, 1.0)
    plan = search_relational(base, queries, layout, codebooks.stride_codebook(base, layout, 8), 8, base.count(), 10, params)
    assert rows(search(build_index(base, PARAMS), queries, 10, params)) == rows(plan)
    assert plan.groupBy("query_id").count().filter("count < 10").count() == 0


def test_optimized_without_limits_is_guaranteed(e64):
    index = build_index(e64[0], PARAMS)
    loose = SearchParams("optimized", 0.2, 0.25, rank_cut=0, eps=1e9, patience_factor=None, block=1)
    assert rows(search(index, e64[1], 10, loose)) == rows(search(index, e64[1], 10, SearchParams("guaranteed", 0.2, 0.25)))


def test_relational_fold_is_the_engine_on_one_shard(spark, e64):
    base, queries = e64
    layout, params = uniform_layout(64, 8), SearchParams("optimized", 0.2, 0.4, rank_cut=10, patience_factor=3, block=1)
    plan = search_relational(base, queries, layout, codebooks.stride_codebook(base, layout, 8), 8, base.count(), 10, params)
    index = build_index(base, replace(PARAMS, shard_rows=10**6))
    assert rows(search(index, queries, 10, params)) == rows(plan.select("query_id", "rank", "id", "dist2"))


def test_candidates_move_with_parameters(e64):
    index = build_index(e64[0], PARAMS)
    size = lambda **p: counters(search(index, e64[1], 10, replace(SearchParams("guaranteed", 0.2, 0.25), **p), details=True)).agg(F.sum("candidates")).first()[0]
    by_ratio = [size(ratio=r) for r in (0.05, 0.1, 0.2, 0.4)]
    by_fraction = [size(min_fraction=f) for f in (0.1, 0.3, 0.5, 0.8)]
    assert by_ratio == sorted(by_ratio) and by_fraction == sorted(by_fraction, reverse=True)
    assert size(mode="optimized") >= size()  # double votes under the same threshold


def test_index_round_trip_append_and_footprint(spark, e64, truth, tmp_path):
    base, queries = e64
    index = build_index(base.filter("id % 2 = 0"), PARAMS)
    index = append(index, base.filter("id % 2 = 1"))
    full = SearchParams("guaranteed", 1.0, 0.1)
    assert rows(search(index, queries, 10, full)) == rows(truth)
    save_index(index, str(tmp_path / "i"))
    again = load_index(spark, str(tmp_path / "i"), PARAMS)
    assert rows(search(again, queries, 10, full)) == rows(truth)
    with pytest.raises(ValueError):
        load_index(spark, str(tmp_path / "i"), replace(PARAMS, m=4))
    parts = {r["component"]: r["bytes"] for r in footprint(index).collect()}
    assert parts["vectors"] == 8 * 64 * index.n and parts["rows"] == 4 * 8 * index.n and parts["words"] == 8 * index.n


def test_rotated_index_finds_all(spark, sf):
    base, queries = sources.split(sources.vectors(spark, sf, "E64-decay90"))
    for kind in ("gaussian", "hadamard"):
        index = build_index(base, replace(PARAMS, policy="adaptive", rotation=kind))
        assert index.report.rotate
        got = search(index, queries, 5, SearchParams("guaranteed", 1.0, 0.1))
        assert rows(got.select("query_id", "rank", "id")) == rows(exact.knn(base, queries, 5).select("query_id", "rank", "id"))


def test_edge_cases(spark):
    one = spark.createDataFrame([(1, [1.0, 2.0, 3.0, 4.0])], "id long, vec array<double>")
    index = build_index(one, IndexParams(m=1, k=2, iters=1, storage="f8"))
    assert rows(search(index, one, 3)) == [(1, 1, 1, 0.0)]
    same = spark.createDataFrame([(i, [1.0, 1.0, 0.0]) for i in range(5)], "id long, vec array<double>")
    got = search(build_index(same, IndexParams(m=1, k=4, iters=2, storage="f8")), same.limit(1), 3)
    assert [r["id"] for r in got.orderBy("rank").collect()] == [0, 1, 2]
    with pytest.raises(ValueError):
        build_index(one.limit(0), PARAMS)
    with pytest.raises(ValueError):
        build_index(one.union(spark.createDataFrame([(2, [1.0])], one.schema)), PARAMS)


def test_spectral_decisions(spark, sf):
    for code, rotate in (("E64", False), ("E64-decay90", True), ("E64-mix", True), ("E64-decay95", False)):
        df = sources.vectors(spark, sf, code)
        report = spectral.check(df, df.count(), 64)
        assert report.rotate == rotate and not report.rank_deficient
    docs = sources.documents(spark, sf, 768)
    assert spectral.check(docs, docs.count(), 768, rule="paper").rank_deficient
    assert not spectral.decide(0.85) and spectral.decide(0.8501) and spectral.decide(0.1, policy="always") and not spectral.decide(0.99, policy="never")


def test_cev_agrees_with_spark_pca(spark, sf):
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector

    df = sources.embeddings(spark, sf)
    _, cov = spectral.covariance_matrix(df, 64)
    model = PCA(k=12, inputCol="v", outputCol="o").fit(df.select(array_to_vector("vec").alias("v")))
    assert spectral.cev(spectral.eigenvalues(cov)) == pytest.approx(float(sum(model.explainedVariance)), abs=1e-9)


@settings(max_examples=20, deadline=None)
@given(st.integers(2, 40), st.integers(0, 1000))
def test_rotations_are_orthogonal(dim, seed):
    r = rotation.gaussian_qr(dim, seed)
    assert np.allclose(r @ r.T, np.eye(dim), atol=1e-9)
    x = np.random.default_rng(seed).standard_normal((3, dim))
    assert np.allclose(np.linalg.norm(rotation.hadamard(x, rotation.hadamard_signs(dim, seed)), axis=1), np.linalg.norm(x, axis=1))
    b = rotation.block(dim, np.arange(0, dim, 2), seed)
    assert np.allclose((x @ b)[:, 1::2], x[:, 1::2])


@settings(max_examples=30, deadline=None)
@given(st.integers(1, 8), st.integers(0, 60))
def test_layouts_cover_each_dimension_once(m, more):
    dim = 2 * m + more
    variances = np.random.default_rng(more).random(dim) + 0.01
    for layout in (uniform_layout(dim, m), variance_layout(variances, m)):
        assert layout.m == m and layout.starts[0] == 0
        assert [s + n for s, n in zip(layout.starts, layout.lengths, strict=True)] == [*layout.starts[1:], dim]


def test_walk_on_a_small_grid():
    left, right = np.array([0.0, 1.0, 2.5, 4.0, 7.0]), np.array([0.0, 0.9, 2.0, 5.0, 6.0])
    visited = list(activation.walk(left, right))
    assert visited[:6] == [(0, 0, 0.0), (0, 1, 0.9), (1, 0, 1.0), (1, 1, 1.9), (0, 2, 2.0), (2, 0, 2.5)]
    assert len(visited) == 25 and [c for _, _, c in visited] == sorted(c for _, _, c in visited)
    counts = np.full(25, 3)
    counts[1] = 0  # an empty cell uses a rank; the last cell overshoots
    got, pulled = activation.activate(left, right, counts, 7)
    assert got.tolist() == [0, 1, 5, 6] and pulled == 9


@settings(max_examples=60, deadline=None)
@given(st.integers(0, 10**6), st.integers(1, 7), st.integers(1, 60))
def test_walk_equals_sorting_all_cells(seed, k, limit):
    rng = np.random.default_rng(seed)
    left, right, counts = np.round(rng.random(k), 1), np.round(rng.random(k), 1), rng.integers(0, 4, k * k)
    lo, ro = np.argsort(left, kind="stable"), np.argsort(right, kind="stable")
    order = sorted((round(left[a] + right[b], 9), i, j, a * k + b) for i, a in enumerate(lo) for j, b in enumerate(ro))
    want, before = [], 0
    for *_, cell in order:
        if before >= limit:
            break
        want.append(cell)
        before += counts[cell]
    assert activation.activate(left, right, counts, limit)[0].tolist() == want


def test_csr_example():
    cells_ = np.array([[1], [0], [1], [1], [0], [3]])
    starts, order = cells.csr(cells_, 4)
    assert starts.tolist() == [[0, 2, 5, 5, 6]] and order.tolist() == [[1, 4, 0, 2, 3, 5]]


def test_sign_words_and_hamming(spark, e64):
    x = np.random.default_rng(3).standard_normal((6, 130))
    df = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "id long, vec array<double>")
    got = np.array([r[0] for r in df.orderBy("id").select(V.sign_words(F.col("vec"), 130)).collect()])
    assert (got == sign_words(x)).all()
    pairs = df.alias("a").crossJoin(df.alias("b")).select(F.col("a.id"), F.col("b.id"), V.hamming(V.sign_words(F.col("a.vec"), 130), V.sign_words(F.col("b.vec"), 130)))
    for i, j, h in pairs.collect():
        assert h == ((x[i] >= 0) != (x[j] >= 0)).sum()


def test_fold_prunes_and_stops():
    q, near, far = np.zeros(64), np.full(64, 0.1), np.zeros(64)
    far[0] = 100.0
    late = np.zeros(64)
    late[63] = 100.0
    x, ids = np.stack([near, far, late, near * 2]), np.array([10, 11, 12, 13])
    best, c, pruned = refine.fold(x, ids, q, 1)
    assert best[0][1] == 10 and pruned == [11, 13] and c.completed == 2 and c.dims == 32 + 32 + 32 + 32 + 64
    best, c, _ = refine.fold(x, ids, q, 1, patience=2, sampling=False)
    assert c.stopped == 1 and c.started == 3
    assert refine.fold(x, ids, q, 3, eps=1e9)[0] == refine.fold(x, ids, q, 3, sampling=False)[0]
    assert refine.fold(x[:0], ids[:0], q, 3)[0] == []


def test_bounds_hold(spark):
    points = spark.createDataFrame([(m, p, f * m) for m in (2, 8, 32) for p in (0.3, 0.6, 0.95) for f in (0.1, 0.25, 0.5, 0.9)], "m int, p double, tau double")
    for r in bounds.table(points).collect():
        tail = sum(math.comb(r.m, s) * r.p**s * (1 - r.p) ** (r.m - s) for s in range(math.ceil(r.tau), r.m + 1))
        assert r.exact == pytest.approx(tail, abs=1e-9)
        assert r.hoeffding <= tail + 1e-9 and r.chebyshev <= tail + 1e-9
    tight = {(r.m, r.p): r.tighter for r in bounds.table(spark.createDataFrame([(8, 0.95, 4.0), (32, 0.6, 10.0)], "m int, p double, tau double")).collect()}
    assert tight == {(8, 0.95): "chebyshev", (32, 0.6): "hoeffding"}
    assert 1 - math.exp(-2 * (20 * 0.8 - bounds.largest_threshold(20, 0.8, 0.05)) ** 2 / 20) == pytest.approx(0.95)


def test_onebit_estimator_is_unbiased():
    rng = np.random.default_rng(0)
    x, q = rng.standard_normal((40, 96)), rng.standard_normal(96)
    errors, held = [], []
    for seed in range(30):
        r = rotation.gaussian_qr(96, seed)
        guess, low = onebit_ivf.estimate(*onebit_ivf.codes_of(x @ r), q @ r)
        true = ((x - q) ** 2).sum(axis=1)
        errors.append(((guess - true) / true).mean())
        held.append((low <= true + 1e-9).mean())
    assert abs(np.mean(errors)) < 0.01 and np.mean(held) > 0.9


def test_baselines(spark, sf, e64, truth):
    base, queries = e64
    ivf = onebit_ivf.build(base, 64, 8, 3)
    recall = [metrics.recall(onebit_ivf.search(ivf, queries, 10, p), truth, 10).first()["recall"] for p in (1, 4, 8)]
    assert recall == sorted(recall) and recall[-1] > 0.95
    assert rows(onebit_ivf.search(ivf, queries, 10, 8, eps=99.0)) == rows(truth)
    errors = learned_pq.train(sources.vectors(spark, sf, "E64-mix"), 64, 8, bits=3, iters=5).errors
    assert all(b <= a * 1.0001 for a, b in zip(errors, errors[1:], strict=False))
    world = graph.build(base, 16, 64, 2)
    assert metrics.recall(graph.search(world, queries, 10, 5000), truth, 10).first()["recall"] > 0.99


def test_lloyd_error_falls(e64):
    _, errors = codebooks.train(e64[0], uniform_layout(64, 4), 8, 6)
    assert all(b <= a + 1e-9 for a, b in zip(errors, errors[1:], strict=False))


def test_lid_of_a_known_dimension(spark):
    df = sources.synthetic(spark, 1500, 40, latent=5, partitions=4)
    base, queries = sources.split(df, 15)
    r = metrics.lid_summary(metrics.lid(exact.knn(base, queries, 30), 30)).first()
    assert 3.5 < r["mean_lid"] < 6.5
    flat = spark.createDataFrame([(1, k, 4.0) for k in range(1, 5)], "query_id long, rank int, dist2 double")
    assert metrics.lid_summary(metrics.lid(flat, 4)).first()["used"] == 0


def test_filters_and_planner(spark, sf, e64):
    base, queries = e64
    pre = filtered_knn(base, queries, 3, F.col("id") % 2 == 1)
    assert pre.filter("id % 2 = 0").count() == 0 and pre.count() == 3 * queries.count()
    wide = filtered_knn(base, queries, 3, F.col("id") % 2 == 1, "post", 50)
    assert rows(wide) == rows(pre)
    assert choose(10**9, 1024, 100, None) == "exact" and choose(10**3, 8, 1, object()) == "exact" and choose(10**9, 1024, 100, object()) == "index"
    assert candidates.tau(0.25, 8) == 2 and candidates.tau(0.26, 8) == 3 and activation.budget(0.2, 450) == 90


@pytest.mark.parametrize("mode, cut", [("guaranteed", None), ("optimized", 4)])
def test_places_of_cells_stand_for_lists(spark, monkeypatch, mode, cut):
    """Both forms of an activation, as cells and as the places of the last ones, give the same rows."""
    df = sources.synthetic(spark, 600, 16, partitions=3)
    index = engine.build_index(df.filter("id >= 20"), engine.IndexParams(m=4, k=9, iters=2, policy="never", shard_rows=200, storage="f8"))
    params = engine.SearchParams(mode, 0.1, 0.5, rank_cut=cut)
    queries = df.filter("id < 20")
    want = sorted(engine.search(index, queries, 5, params).collect())
    monkeypatch.setattr(engine, "ACTIVE_BYTES", 0)
    assert sorted(engine.search(index, queries, 5, params).collect()) == want


def test_large_codebooks(spark):
    """700 centroids a half: 490,000 cells a subspace, of which shards store the occupied ones only."""
    df = sources.synthetic(spark, 6000, 16, latent=3, partitions=4).persist()
    index = engine.build_index(df, engine.IndexParams(m=4, k=700, iters=1, policy="never", shard_rows=2000))
    stored = engine.footprint(index).filter("component = 'offsets'").first()["bytes"]
    assert stored < 6000 * 4 * 12
    queries = df.filter("id % 500 = 0")
    got = engine.search(index, queries, 3, engine.SearchParams("guaranteed", 0.1, 0.5))
    recall = metrics.recall(got, exact.knn(df, queries, 3), 3).first()["recall"]
    assert recall > 0.9


def test_copies_at_the_boundary_go_by_id(spark):
    """Thousands of equal vectors: the smallest ids stay, however rows are spread."""
    rows = [(i, [1.0, 2.0, 3.0, 4.0]) for i in range(900)] + [(1000 + i, [float(i), 0.0, 0.0, 0.0]) for i in range(50)]
    df = spark.createDataFrame(rows, "id long, vec array<double>")
    queries = spark.createDataFrame([(0, [1.0, 2.0, 3.0, 4.0])], "id long, vec array<double>")
    assert [r["id"] for r in exact.knn(df.repartition(2), queries, 5).orderBy("rank").collect()] == [0, 1, 2, 3, 4]
    index = engine.build_index(df, engine.IndexParams(m=2, k=4, iters=1, policy="never", shard_rows=2000))
    got = engine.search(index, queries, 5, engine.SearchParams("guaranteed", 1.0, 0.01)).orderBy("rank").collect()
    assert [r["id"] for r in got] == [0, 1, 2, 3, 4]
