"""Workloads run on the smallest tables and their figures keep the relations they are about."""

from dataclasses import replace

from subvote.operators.engine import SearchParams, pair_votes, search
from subvote.plans import workloads


def test_memory_of_all_methods(spark, sf):
    size = {}
    for r in workloads.memory(spark, sf).collect():
        size[r["method"]] = size.get(r["method"], 0.0) + r["of_raw"]
    assert set(size) == {"method", "uniform-collision", "learned-pq", "onebit-ivf", "graph"}
    assert size["method"] < size["uniform-collision"] < size["graph"] + size["onebit-ivf"]


def test_bounds_hold(spark, sf):
    rows = workloads.bound_check(spark, sf, seeds=1).collect()
    assert len(rows) == 3
    for r in rows:
        assert 0 <= r["p"] <= 1 and r["chebyshev"] <= r["hoeffding"] + 1e-9 <= r["nn_found"] + 0.1 and r["nn_found"] <= r["nn_touched"]


def test_thresholds_and_latency(spark, sf):
    rows = workloads.threshold_sweep(spark, sf, (0.2, 0.85, 1.01), ("E64-decay90",)).collect()
    assert [r["rotated"] for r in rows] == [True, True, False] and all(r["ms_per_query"] > 0 for r in rows)
    assert rows[0]["recall"] >= rows[2]["recall"]


def test_grid_rows(spark, sf):
    rows = workloads.grids(spark, sf, "E64", (8,), (0.06, 0.4), (0.15, 0.25), (2,)).collect()
    by = {(r["mode"], r["ratio"], r["fraction"]): r["recall"] for r in rows}
    assert len(by) == 8 and by["guaranteed", 0.4, 0.25] >= by["guaranteed", 0.06, 0.25]


def test_votes_of_given_pairs(spark, sf):
    """The votes of chosen pairs are those of a whole search, and no other row leaves the shards."""
    b = workloads.Bench(spark, sf, "E64")
    index, _ = b.build(replace(workloads.BUILD, m=8, iters=3, shard_rows=100))
    pairs = b.truth.filter("rank <= 2").select("query_id", "id")
    got = {(r["query_id"], r["id"]): r["score"] for r in pair_votes(index, b.queries, pairs, 0.2).collect()}
    whole = search(index, b.queries, b.n, SearchParams("guaranteed", 0.2, 1 / 8), details=True).filter("kind = 'near'").join(pairs, ["query_id", "id"])
    assert got and got == {(r["query_id"], r["id"]): r["score"] for r in whole.collect()}
