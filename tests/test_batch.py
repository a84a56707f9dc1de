"""Many queries against a shard at once give what the fold gives query by query."""

import numpy as np
import pytest

from subvote.operators import activation, batch, graph, onebit_ivf, refine
from subvote.operators.arrow import sign_words
from subvote.operators.engine import IndexParams, SearchParams, build_index, search
from subvote.operators.subspaces import uniform_layout
from subvote.sources import vectors as sources


@pytest.mark.parametrize("patience", [None, 3, 40])
@pytest.mark.parametrize(("sampling", "step", "hamming"), [(True, 8, True), (True, 32, False), (False, 32, True)])
@pytest.mark.parametrize("block", [1, 32])
@pytest.mark.parametrize(("n", "k"), [(5, 10), (128, 10), (700, 3), (700, 100)])
def test_same_as_one_query_at_a_time(monkeypatch, patience, sampling, step, hamming, block, n, k):
    monkeypatch.setattr(batch, "AHEAD", 64)
    monkeypatch.setattr(batch, "PAIRS", 3000)
    monkeypatch.setattr(batch, "FOLDED", 4000)
    rng = np.random.default_rng(n + k)
    x = np.round(rng.normal(size=(n, 64)), 1)
    x[n // 2 :] = x[: n - n // 2]  # copies: ties in distance
    x[: n // 4] = x[0]
    names, q = np.sort(rng.choice(10 * n, n, replace=False)), np.concatenate([x[: min(n, 20)], np.round(rng.normal(size=(20, 64)), 1)])
    words, asked = sign_words(x), sign_words(q)
    score = rng.integers(0, 17, size=(len(q), n)).astype(np.int8)
    score[3] = 0
    shard = batch.Shard(names, x, words, step)
    assert shard.fits(q)
    seen = 0
    for at, d2, place, passed, dims, started in shard.verify(q, asked, lambda i: score[i], 6, 16, k, 0.4, patience, hamming, sampling, block):
        for i, *got in zip(at.tolist(), d2, place, passed, dims, started, strict=True):
            rows = np.flatnonzero(score[i] >= 6)
            keys = (names[rows], -score[i, rows])
            keys = (*keys, np.bitwise_count((words[rows] ^ asked[i]).view(np.uint64)).sum(axis=1)) if hamming else keys
            rows = rows[np.lexsort(keys)]
            best, c, _ = refine.fold(x[rows], names[rows], q[i], k, step, 0.4, patience, sampling, block)
            held = got[1] >= 0
            assert list(zip(got[0][held].tolist(), names[got[1][held]].tolist(), strict=True)) == best
            assert (int(got[2]), int(got[3]), int(got[4])) == (len(rows), c.dims, c.started)
            seen += 1
    assert seen == len(q)


def test_long_vectors_and_repeated_ids_are_told():
    x = np.ones((4, 8))
    assert not batch.Shard(np.array([1, 2, 2, 3]), x, sign_words(x), 4).fits(x)
    assert not batch.Shard(np.arange(4), 1e12 * x, sign_words(x), 4).fits(x)
    assert not batch.Shard(np.arange(4), np.nan * x, sign_words(x), 4).fits(x)


def test_a_task_sends_k_rows_of_a_query_whatever_its_shards(spark, sf):
    base, queries = sources.split(sources.embeddings(spark, sf))
    index = build_index(base, IndexParams(m=8, k=8, iters=2, shard_rows=10, storage="f8"))
    for mode in ("guaranteed", "optimized"):
        raw = search(index, queries, 5, SearchParams(mode, 0.3, 0.25), details=True)
        tasks = raw.rdd.getNumPartitions()
        per = raw.filter("kind = 'near'").groupBy("query_id").count().collect()
        assert tasks < index.shards.count() and per and max(r["count"] for r in per) <= 5 * tasks


@pytest.mark.parametrize(("k", "limit", "rank_cut"), [(8, 60, 3), (8, 1, 0), (8, 100_000, 10), (40, 25, 2)])
def test_weights_of_all_cells_are_those_of_the_walk(k, limit, rank_cut):
    rng = np.random.default_rng(k)
    layout = uniform_layout(16, 2)
    books = [np.round(rng.normal(size=(k, w)), 0) for w in layout.lengths]  # ties in cost
    counts = rng.integers(0, 3, size=(2, k * k)) * (rng.random((2, k * k)) < 0.2)
    q = np.round(rng.normal(size=(30, 16)), 0)
    half = activation.half_matrix(q, layout, books)
    table = activation.weight_table(q, layout, books, counts, limit, rank_cut).reshape(30, 2, -1)
    for i in range(30):
        for m in range(2):
            cells, _ = activation.activate(half[2 * m][i], half[2 * m + 1][i], counts[m], limit)
            want = np.zeros(k * k, np.int8)
            want[cells] = 1
            want[cells[:rank_cut]] = 2
            assert (table[i, m] == want).all()


def test_graphs_and_clusters_meet_in_several_tasks(spark, sf):
    base, queries = sources.split(sources.embeddings(spark, sf))
    world = graph.build(base, 8, 32, 4)
    assert world.graphs.rdd.getNumPartitions() > 4
    found = graph.search(world, queries, 5, 32)
    assert "Repartition" in found._jdf.queryExecution().optimizedPlan().toString()
    assert found.groupBy("query_id").count().filter("count = 5").count() == queries.count()
    assert onebit_ivf.build(base, 64, 8, 2).clusters.rdd.getNumPartitions() > 8


def test_votes_of_picked_queries():
    rng = np.random.default_rng(2)
    table, places = rng.integers(0, 3, size=(64, 40)).astype(np.int8), rng.integers(0, 64, size=(900, 8))
    some = np.array([7, 3, 30])
    assert (batch.votes(table[:, some], places) == table[:, some][places].sum(axis=1).T).all()
