"""Queries on tables larger or more split than the given ones: the SQL form holds there too."""

from dataclasses import replace

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from subvote.operators import candidates, exact, metrics, refine, scoring, whole
from subvote.operators.engine import IndexParams, SearchParams, build_index, search
from subvote.plans import ann
from subvote.sources import vectors as sources
from tests.test_queries import table


@pytest.fixture
def same(spark, tmp_path):
    """Compares a query with its SQL on tables made for the test."""

    def compare(name, **tables):
        con = duckdb.connect()
        for t, sql in tables.items():
            con.execute(f"COPY ({sql}) TO '{tmp_path}/{t}.parquet' (FORMAT parquet)")
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet'")
        df = entry.queries()[name](spark, str(tmp_path))
        res = con.execute(entry.oracle_sql()[name])
        columns = [c[0] for c in res.description]
        normal = lambda rows: [tuple(float(v) if isinstance(v, (int, float)) and not isinstance(v, bool) else v for v in r) for r in rows]
        assert table(df.columns, normal(df.collect())) == table(columns, normal(res.fetchall()))

    return compare


def test_bit_aggs_beyond_one_bitmap(same):
    same("q_bit_aggs", embeddings="SELECT range::BIGINT AS vec_id, [1.0::FLOAT] AS embedding, (range % 3)::INT AS label FROM range(100000)")


def test_sort_nulls_over_many_partitions(spark, same):
    before = {k: spark.conf.get(k) for k in ("spark.sql.shuffle.partitions", "spark.sql.adaptive.advisoryPartitionSizeInBytes")}
    spark.conf.set("spark.sql.shuffle.partitions", "12")
    spark.conf.set("spark.sql.adaptive.advisoryPartitionSizeInBytes", "1m")
    try:
        customers = "SELECT CASE WHEN range % 2 = 0 THEN range ELSE -range END::BIGINT AS c_custkey, CASE WHEN range % 31 < 25 THEN range % 31 END::INT AS c_nationkey FROM range(300000)"
        same("q_sort_nulls", customer=customers)
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)


def test_exact_neighbours_join_blocks(spark):
    """Blocks of vectors are joined, not single pairs; copies, ties and null vectors included."""
    x = np.round(np.random.default_rng(3).normal(size=(3000, 5)), 2)
    x[1500:1700] = x[:200]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)] + [(-1, None)], "id long, vec array<double>")
    base, queries = df.filter("id % 3 != 0"), df.filter("id % 3 = 0")
    found = exact.knn_relational(base, queries, 4)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "zip_with" not in plan
    got = {(r["query_id"], r["rank"]): (r["id"], r["dist2"]) for r in found.collect()}
    ids = np.flatnonzero(np.arange(3000) % 3)
    want = {}
    for q in range(0, 3000, 3):
        d2 = np.round(((x[ids] - x[q]) ** 2).sum(axis=1), 6)
        want |= {(q, rank): (int(ids[i]), float(d2[i])) for rank, i in enumerate(np.lexsort((ids, d2))[:4], start=1)}
    assert got == want


#: Queries that measured every pair as a row, with more columns of their own around it.
BLOCKED = ["q_exact_knn", "q_exact_nn1", "q_filtered_knn_post", "q_label_purity", "q_lid", "q_estimate_p", "q_dependence", "q_bounds_het"]


@pytest.mark.parametrize("name", BLOCKED)
def test_truth_is_read_from_blocks(spark, sf, name):
    plan = entry.queries()[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "base_vecs" in plan and "zip_with(vec" not in plan


def test_label_purity_counts_no_base(spark, sf):
    """It needs no codebook, so nothing but the schema is read before its one plan runs."""
    spark.sparkContext.setJobGroup("label_purity", "made, not run")
    try:
        entry.queries()["q_label_purity"](spark, sf)
        assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("label_purity")) <= 1
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


@pytest.mark.parametrize("fraction", [0.25, 0.5, 0.9, 1.0])
def test_counts_of_candidates_without_their_rows(spark, sf, fraction):
    """Dense counts give what the rows of the candidates give, with and without the fallback."""
    s = ann.Small(spark, sf)
    params = replace(ann.GUARANTEED, min_fraction=fraction)
    rows, active, assigned = s.stage(params, "candidates").persist(), s.stage(params, "activations").persist(), s.assigned().persist()
    dense, truth = s.summary(params, active, assigned), s.truth().persist()
    assert tuple(metrics.summary_stats(dense, s.n, ann.TOP).first()) == pytest.approx(tuple(metrics.candidate_stats(rows, s.n).first()), rel=1e-12)
    pairs = scoring.pair_scores(active, assigned, truth, 0)
    found = metrics.summary_recall(dense, pairs, candidates.tau(fraction, ann.M), ann.TOP).first()
    assert tuple(found) == pytest.approx(tuple(metrics.candidate_recall(rows, truth, ann.TOP).first()), rel=1e-12)


#: Queries that made a row of every vote.
COUNTED = ["q_candidate_stats", "q_candidate_recall"]


@pytest.mark.parametrize("name", COUNTED)
def test_votes_are_not_rows(spark, sf, name):
    plan = entry.queries()[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "query_weights" in plan


@pytest.mark.parametrize("change", [{"use_hamming": False}, {"use_sampling": False}, {"patience_factor": None}, {"min_fraction": 1.6}])
def test_optimized_search_in_blocks(spark, sf, monkeypatch, change):
    """Blocks give what rows of votes, candidates and measures give, with and without the fallback."""
    monkeypatch.setattr(whole, "BASE_ROWS", 97)
    s, params = ann.Small(spark, sf), replace(ann.OPTIMIZED, **change)
    columns = ["query_id", "rank", "id", "dist2", "started", "completed", "pruned", "dims", "stopped"]
    got = s.stage(params)
    patience = None if params.patience_factor is None else int(params.patience_factor * ann.TOP)
    rows = refine.fold_queries(s.stage(params, "ordered"), s.base, s.queries, ann.TOP, patience=patience, sampling=params.use_sampling).persist()
    assert sorted(got.select(columns).collect()) == sorted(rows.select(columns).collect())
    truth = s.truth().persist()
    pruned = rows.select("query_id", F.explode("pruned_ids").alias("id"))
    assert tuple(metrics.false_prunes(got, truth).first()) == (pruned.join(truth, ["query_id", "id"]).count(), pruned.count())


#: Optimized searches that made a row of every vote and candidate.
DENSE = ["q_ablate_no_hamming", "q_ablate_no_sampling", "q_dim_sampling", "q_false_prunes"]


@pytest.mark.parametrize("name", DENSE)
def test_candidates_are_not_rows(spark, sf, name):
    plan = entry.queries()[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "base_cells" in plan and "zip_with" not in plan


def test_shards_are_searched_once(spark, sf):
    """One pass over the shards, which are dealt to all cores even where one shard holds the whole table."""
    b, k = ann.Small(spark, sf), 3
    found = []
    for shard_rows in (64, 1 << 20):
        index = build_index(b.base, IndexParams(m=8, k=8, iters=2, policy="never", shard_rows=shard_rows, storage="f8"))
        for fraction in (0.25, 1.0):  # the second leaves most queries to the fallback
            out = search(index, b.queries, k, SearchParams("guaranteed", 0.05, fraction))
            plan = out._jdf.queryExecution().optimizedPlan().toString()
            assert plan.count("MapInArrow run") == 1
            assert search(index, b.queries, k, details=True).rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism
            found.append(sorted(out.collect()))
            assert len(found[-1]) == k * b.queries.count()
    assert found[:2] == found[2:] and found[0] != found[1]


def test_hashed_text_is_dealt_out(spark, sf):
    plan = sources.documents(spark, sf, 768)._jdf.queryExecution().optimizedPlan().toString()
    assert "element_at" not in plan and "Repartition" in plan


#: Queries on activated cells that made a row of every half distance and every cell of the grids.
CELLS = ["q_estimate_p", "q_bounds_het", "q_dependence", "q_candidate_recall"]


@pytest.mark.parametrize("name", CELLS)
def test_grids_are_not_rows(spark, sf, name):
    plan = entry.queries()[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "query_weights" in plan and "zip_with" not in plan and "half_rank" not in plan


def test_order_comes_in_runs():
    """Runs in order are the whole order, and the first of them leaves the rest unsorted."""
    rng = np.random.default_rng(5)
    for n, least in ((20_000, 3), (20_000, 9), (700, 3)):
        score, key = rng.integers(0, 10, n).astype(np.int16), rng.integers(0, 1100, n).astype(np.int16)
        runs = list(whole.runs_in_order(score, key, least, 10))
        assert np.array_equal(np.concatenate(runs), whole.candidates_in_order(score, key, least, 10))
        assert len(runs[0]) < 1000 and len(runs) < 8
    assert [len(r) for r in whole.runs_in_order(score, key, 10, 10)] == [10]
