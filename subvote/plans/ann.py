"""Queries of the method, its variants, baselines and measures on the embedding table.

Rows with id divisible by 10 ask, the others answer.  Where a query has an SQL form, the
codebooks are the id-stride start (no randomness), so both sides share every stage.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subvote.functions import bounds
from subvote.functions import vectors as V
from subvote.operators import activation, candidates, cells, codebooks, exact, graph, learned_pq, lsh, metrics, onebit_ivf, refine, rotation, scoring, spectral, uniform_collision, whole
from subvote.operators.engine import IndexParams, SearchParams, append, build_index, counters, filtered_knn, footprint, knn_join, load_index, save_index, search, search_filtered, search_relational
from subvote.operators.subspaces import uniform_layout, variance_layout
from subvote.session import scratch
from subvote.sources import vectors as sources
from subvote.sources.tables import load

DIM, M, K, TOP = 64, 8, 8, 10
RATIO, FRACTION = 0.2, 0.25
GUARANTEED = SearchParams("guaranteed", RATIO, FRACTION)
OPTIMIZED = SearchParams("optimized", RATIO, 0.4, rank_cut=TOP, patience_factor=4, block=1)


class Small:
    """The tables of one run: base, queries, layout, id-stride codebooks."""

    def __init__(self, spark: SparkSession, sf_dir: str, code: str = "E64", rotate: Callable[[DataFrame], DataFrame] | None = None):
        df = sources.vectors(spark, sf_dir, code)
        self.spark, self.df = spark, rotate(df) if rotate else df
        self.base, self.queries = sources.split(self.df)
        self.layout = uniform_layout(DIM, M)
        self.books = codebooks.stride_codebook(self.base, self.layout, K)
        self.n = self.base.count()

    def assigned(self) -> DataFrame:
        return cells.encode_relational(self.base, self.layout, self.books, K)

    def stage(self, params: SearchParams, stage: str = "result") -> DataFrame:
        return search_relational(self.base, self.queries, self.layout, self.books, K, self.n, TOP, params, stage)

    def summary(self, params: SearchParams, active: DataFrame, assigned: DataFrame) -> DataFrame:
        """Counts of the candidates of every query, in place of one row each."""
        return scoring.summary(active, assigned, 0, candidates.tau(params.min_fraction, M), TOP, M, K * K)

    def votes(self, params: SearchParams) -> tuple[DataFrame, DataFrame]:
        """(id, cells) of the base and the weights of every cell for blocks of queries, both in Arrow batches."""
        books = codebooks.arrays(self.books, self.layout)
        codes = cells.encode_exact(self.base, self.layout, books)
        counts = cells.count_matrix(codes, M, K * K)
        return codes, whole.tables(self.queries, self.layout, books, counts, activation.budget(params.ratio, self.n), 0, 256)

    def truth(self, k: int = TOP) -> DataFrame:
        return exact.knn_relational(self.base, self.queries, k)


def q_exact_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Small(spark, sf_dir).truth()


def q_exact_nn1(spark, sf_dir):
    return Small(spark, sf_dir).truth(1)


def q_exact_knn_bulk(spark, sf_dir):
    base, queries = sources.split(sources.embeddings(spark, sf_dir))
    return exact.knn(base, queries, TOP)


def q_radius_search(spark, sf_dir):
    base, queries = sources.split(sources.embeddings(spark, sf_dir))
    return exact.range_search(base, queries, 1.2)


def q_cov_entries(spark, sf_dir):
    df = sources.embeddings(spark, sf_dir).withColumn("vec", F.slice("vec", 1, 8))
    return spectral.covariance(df).withColumn("c", F.round("c", 9))


def q_variance_spread(spark, sf_dir):
    out = metrics.variance_spread(sources.vectors(spark, sf_dir, "E64-decay90"))
    return out.select(F.round("variation", 6).alias("variation"), F.round("ratio", 2).alias("ratio"))


def q_trace_frobenius(spark, sf_dir):
    """Sum and sum of squares of the eigenvalues: trace and squared norm of the covariance."""
    _, cov = spectral.covariance_matrix(sources.embeddings(spark, sf_dir), DIM)
    e = spectral.eigenvalues(cov)
    return spark.createDataFrame([(round(float(e.sum()), 9), round(float((e**2).sum()), 9))], "trace double, frobenius double")


def q_cev_report(spark, sf_dir):
    """Spectral check of every 64-dimensional view and the decision by each policy."""
    rows = []
    for code in ("E64", "E64-decay90", "E64-decay93", "E64-decay95", "E64-mix"):
        df = sources.vectors(spark, sf_dir, code)
        n = df.count()
        for policy, rule in (("adaptive", "guarded"), ("adaptive", "paper"), ("always", "guarded"), ("never", "guarded")):
            r = spectral.check(df, n, DIM, policy=policy, rule=rule)
            rows.append((code, policy, rule, r.rows, r.cev, r.rotate, r.rank_deficient))
    return spark.createDataFrame(rows, "view string, policy string, rule string, rows long, cev double, rotate boolean, rank_deficient boolean")


def q_sample_rule(spark, sf_dir):
    """The bounded sample of the check, by a hash both engines share."""
    df = sources.embeddings(spark, sf_dir)
    return df.filter(F.col("id") % 10 == 0).select("id", F.round(V.norm(F.col("vec")), 6).alias("norm"))


def _signs() -> list[int]:
    return [1 if j % 3 else -1 for j in range(DIM)]


def _hadamard(df: DataFrame) -> DataFrame:
    return df.select("id", V.hadamard(F.col("vec"), _signs()).alias("vec"))


def q_hadamard_rotate(spark, sf_dir):
    out = _hadamard(sources.embeddings(spark, sf_dir)).select("id", F.posexplode("vec").alias("i", "x"))
    return out.filter("i < 4").select("id", "i", F.round("x", 6).alias("x"))


def q_rotate_literal(spark, sf_dir):
    """A plane rotation of the first two dimensions by 30 degrees, through the Arrow kernel."""
    r = np.eye(DIM)
    c, s = math.cos(math.pi / 6), math.sin(math.pi / 6)
    r[:2, :2] = [[c, s], [-s, c]]
    out = rotation.rotate(sources.embeddings(spark, sf_dir), r)
    return out.select("id", *[F.round(F.element_at("vec", j + 1), 6).alias(f"x{j}") for j in range(3)])


def q_rotation_distances(spark, sf_dir):
    """Exact neighbours after a dense random rotation: the same as before."""
    base, queries = sources.split(rotation.rotate(sources.embeddings(spark, sf_dir), rotation.gaussian_qr(DIM)))
    return exact.knn_relational(base, queries, TOP).select("query_id", "rank", "id")


def q_layout_slices(spark, sf_dir):
    s = Small(spark, sf_dir)
    cut = s.base.crossJoin(F.broadcast(s.layout.table(spark)))
    return cut.select("id", "subspace", "half", F.round(V.norm(V.part(F.col("vec"), F.col("start"), F.col("len"))), 6).alias("norm"))


def q_sample_codebook(spark, sf_dir):
    out = Small(spark, sf_dir).books.select("subspace", "half", "code", F.posexplode("centroid").alias("j", "x"))
    return out.select("subspace", "half", "code", "j", F.round("x", 6).alias("x"))


def q_lloyd2_codebook(spark, sf_dir):
    s = Small(spark, sf_dir)
    books, _ = codebooks.train(s.base, s.layout, K, iters=2, init="id_stride", train_rows=None, n=s.n)
    out = codebooks.table(spark, s.layout, books).select("subspace", "half", "code", F.posexplode("centroid").alias("j", "x"))
    return out.select("subspace", "half", "code", "j", F.round("x", 6).alias("x"))


def q_lloyd1_relational(spark, sf_dir):
    s = Small(spark, sf_dir)
    out = codebooks.lloyd_round(s.base, s.layout, s.books).select("subspace", "half", "code", F.posexplode("centroid").alias("j", "x"))
    return out.select("subspace", "half", "code", "j", F.round("x", 6).alias("x"))


def q_encode_cells(spark, sf_dir):
    return Small(spark, sf_dir).assigned().select("id", "subspace", F.col("cell").cast("long").alias("cell"))


def q_encode_cells_bulk(spark, sf_dir):
    s = Small(spark, sf_dir)
    books = codebooks.initial(s.base, s.layout, K, "id_stride", n=s.n)
    return cells.exploded(cells.encode(s.base, s.layout, books)).select("id", "subspace", F.col("cell").cast("long").alias("cell"))


def q_cell_counts(spark, sf_dir):
    return cells.cell_counts(Small(spark, sf_dir).assigned())


def q_cell_skew(spark, sf_dir):
    out = cells.cell_skew(q_cell_counts(spark, sf_dir), K)
    return out.select("subspace", "occupied", *[F.round(c, 6).alias(c) for c in ("empty_share", "max_over_mean", "gini")])


def q_csr_offsets(spark, sf_dir):
    return cells.offsets(q_cell_counts(spark, sf_dir), K)


def q_csr_positions(spark, sf_dir):
    return cells.positions(Small(spark, sf_dir).assigned()).select("subspace", "position", "id")


def q_csr_shards(spark, sf_dir):
    """Posting arrays of four shards, read back as (subspace, cell, id)."""
    s = Small(spark, sf_dir)
    books = codebooks.initial(s.base, s.layout, K, "id_stride", n=s.n)
    packed = cells.build_postings(cells.encode(s.base, s.layout, books), K, 4)
    spans = packed.select("subspace", "offsets", "ids", F.posexplode(F.sequence(F.lit(0), F.lit(K * K - 1))).alias("p", "cell"))
    lo, hi = F.element_at("offsets", F.col("cell") + 1), F.element_at("offsets", F.col("cell") + 2)
    return spans.select("subspace", "cell", F.explode(F.slice("ids", lo + 1, hi - lo)).alias("id"))


def q_map_postings(spark, sf_dir):
    out = cells.map_postings(Small(spark, sf_dir).assigned())
    return out.select("subspace", "cell", F.array_join(F.transform("ids", lambda x: x.cast("string")), ",").alias("ids"))


def q_sign_words(spark, sf_dir):
    df = sources.embeddings(spark, sf_dir)
    return df.select("id", F.element_at(V.sign_words(F.col("vec"), DIM), 1).alias("word"))


def q_half_distances(spark, sf_dir):
    s = Small(spark, sf_dir)
    out = activation.half_distances(s.queries, s.layout, s.books)
    return out.select("query_id", "subspace", "half", "code", F.round("d2", 6).alias("d2"), "half_rank")


def q_grid_activation(spark, sf_dir):
    out = Small(spark, sf_dir).stage(GUARANTEED, "activations")
    return out.select("query_id", "subspace", "cell", "rank", F.col("n").cast("long").alias("n"))


def q_grid_activation_heap(spark, sf_dir):
    s = Small(spark, sf_dir)
    books = codebooks.initial(s.base, s.layout, K, "id_stride", n=s.n)
    counts = np.zeros((M, K * K), np.int64)
    for r in cells.cell_counts(cells.exploded(cells.encode(s.base, s.layout, books))).collect():  # at most M K^2 rows
        counts[r["subspace"], r["cell"]] = r["n"]
    return activation.traverse_heap(s.queries, s.layout, books, counts, activation.budget(RATIO, s.n))


def q_votes_uniform(spark, sf_dir):
    return Small(spark, sf_dir).stage(GUARANTEED, "scores")


def q_votes_weighted(spark, sf_dir):
    return Small(spark, sf_dir).stage(OPTIMIZED, "scores")


def q_votes_own_cell(spark, sf_dir):
    s = Small(spark, sf_dir)
    own = cells.encode_relational(s.queries, s.layout, s.books, K).withColumnRenamed("id", "query_id")
    return scoring.own_cell(own, s.assigned())


def q_double_votes(spark, sf_dir):
    out = scoring.share_of_double_votes(Small(spark, sf_dir).stage(GUARANTEED, "activations"), TOP)
    return out.select("query_id", F.round("double_share", 6).alias("double_share"), F.col("votes").cast("long").alias("votes"), "cells")


def q_threshold(spark, sf_dir):
    return candidates.threshold(q_votes_uniform(spark, sf_dir), candidates.tau(FRACTION, M))


def q_fallback(spark, sf_dir):
    """A threshold no point reaches for most queries: the best k by score fill in."""
    return Small(spark, sf_dir).stage(replace(GUARANTEED, min_fraction=0.9), "candidates").select("query_id", "id", "score", "fallback")


def q_fallback_pad(spark, sf_dir):
    """A tiny budget leaves fewer voted ids than k; ids without votes fill up."""
    s = Small(spark, sf_dir)
    few = s.stage(replace(GUARANTEED, ratio=1e-9, min_fraction=1.0), "candidates").filter("score >= 3")
    return candidates.pad(few, s.base, s.queries, 3).select("query_id", "id", "score")


def q_top_beta(spark, sf_dir):
    s = Small(spark, sf_dir)
    return candidates.top_fraction(s.stage(GUARANTEED, "scores"), 0.05, s.n).select("query_id", "id", "score")


def q_hamming_order(spark, sf_dir):
    return Small(spark, sf_dir).stage(OPTIMIZED, "ordered").select("query_id", "id", "ham", "pos")


def q_dim_sampling(spark, sf_dir):
    """Sampling without patience, over the Hamming order."""
    out = Small(spark, sf_dir).stage(replace(OPTIMIZED, patience_factor=None))
    return out.select("query_id", "rank", "id", "dist2", "completed", "pruned")


def q_patience_exact(spark, sf_dir):
    """Exact verification in Hamming order until 2 k verifications changed nothing."""
    s = Small(spark, sf_dir)
    ordered = refine.distances(s.stage(OPTIMIZED, "ordered"), s.base, s.queries).select("query_id", "pos", "id", "dist2")
    return refine.patience_exact(ordered, TOP, 2 * TOP)


def q_search_guaranteed(spark, sf_dir):
    return Small(spark, sf_dir).stage(GUARANTEED)


def q_search_guaranteed_rotated(spark, sf_dir):
    """Concentrated view, rotated by the signed Hadamard rotation, guaranteed mode."""
    return Small(spark, sf_dir, "E64-decay90", _hadamard).stage(GUARANTEED)


def q_search_optimized(spark, sf_dir):
    return Small(spark, sf_dir).stage(OPTIMIZED).select("query_id", "rank", "id", "dist2", "started", "stopped")


def q_ablate_no_hamming(spark, sf_dir):
    return Small(spark, sf_dir).stage(replace(OPTIMIZED, use_hamming=False)).select("query_id", "rank", "id", "dist2", "started", "stopped")


def q_ablate_no_sampling(spark, sf_dir):
    return Small(spark, sf_dir).stage(replace(OPTIMIZED, use_sampling=False)).select("query_id", "rank", "id", "dist2", "started", "stopped")


def _index(spark: SparkSession, sf_dir: str, code: str = "E64", **more):
    base, queries = sources.split(sources.vectors(spark, sf_dir, code))
    params = IndexParams(m=M, k=K, init="id_stride", iters=0, policy="never", shard_rows=128, storage="f8", train_rows=None)
    return build_index(base, replace(params, **more)), base, queries


def q_engine_guaranteed(spark, sf_dir):
    """The sharded engine; the same rows as the relational plan."""
    index, _, queries = _index(spark, sf_dir)
    return search(index, queries, TOP, GUARANTEED)


def q_engine_optimized(spark, sf_dir):
    index, _, queries = _index(spark, sf_dir, iters=5)
    return search(index, queries, TOP, OPTIMIZED)


def q_engine_adaptive(spark, sf_dir):
    """Build with the check deciding: the concentrated view is rotated."""
    index, _, queries = _index(spark, sf_dir, "E64-decay90", policy="adaptive", iters=5)
    out = search(index, queries, TOP, GUARANTEED)
    return out.withColumn("rotated", F.lit(index.matrix is not None))


def q_engine_counters(spark, sf_dir):
    index, _, queries = _index(spark, sf_dir, iters=5)
    return counters(search(index, queries, TOP, OPTIMIZED, details=True))


def q_engine_append(spark, sf_dir):
    """Half of the base appended later, with frozen codebooks: all of it is found."""
    base, queries = sources.split(sources.embeddings(spark, sf_dir))
    index = build_index(base.filter("id % 2 = 0"), IndexParams(m=M, k=K, iters=3, policy="never", shard_rows=128, storage="f8"))
    index = append(index, base.filter("id % 2 = 1"))
    return search(index, queries, TOP, replace(GUARANTEED, ratio=1.0, min_fraction=0.01))


def q_index_round_trip(spark, sf_dir):
    """Search after saving and loading the index."""
    index, _, queries = _index(spark, sf_dir)
    path = scratch(spark, "index")
    save_index(index, path)
    return search(load_index(spark, path, index.params), queries, TOP, GUARANTEED)


def q_footprint(spark, sf_dir):
    return footprint(_index(spark, sf_dir)[0])


def q_uniform_collision(spark, sf_dir):
    s = Small(spark, sf_dir)
    postings = uniform_collision.build(s.base, s.layout, s.books, K)
    return uniform_collision.search(s.base, postings, s.queries, s.layout, s.books, K, s.n, TOP, RATIO, 0.1)


def q_plain_pq(spark, sf_dir):
    """Product quantisation without rotation: codebooks are the id-stride start, no rounds."""
    s = Small(spark, sf_dir)
    layout = learned_pq.slices(DIM, M)
    books = codebooks.initial(s.base, layout, K, "id_stride", n=s.n)
    return learned_pq.search(s.base, learned_pq.PqModel(layout, np.eye(DIM), books, []), s.queries, TOP)


def q_onebit_ivf(spark, sf_dir):
    base, queries = sources.split(sources.embeddings(spark, sf_dir))
    return onebit_ivf.search(onebit_ivf.build(base, DIM, 8, 5), queries, TOP, 4)


def q_onebit_ivf_full(spark, sf_dir):
    """All clusters probed with a bound that holds always: exact."""
    base, queries = sources.split(sources.embeddings(spark, sf_dir))
    return onebit_ivf.search(onebit_ivf.build(base, DIM, 8, 5), queries, TOP, 8, eps=50.0)


def q_learned_pq(spark, sf_dir):
    base, queries = sources.split(sources.vectors(spark, sf_dir, "E64-mix"))
    return learned_pq.search(base, learned_pq.train(base, DIM, M, bits=4, iters=4), queries, TOP, rerank=40)


def q_learned_pq_errors(spark, sf_dir):
    base, _ = sources.split(sources.vectors(spark, sf_dir, "E64-mix"))
    rows = []
    for learn in (False, True):
        model = learned_pq.train(base, DIM, M, bits=4, iters=5, learn=learn)
        rows += [(learn, i, e) for i, e in enumerate(model.errors)]
    return spark.createDataFrame(rows, "learned boolean, round int, error double")


def q_graph(spark, sf_dir):
    base, queries = sources.split(sources.embeddings(spark, sf_dir))
    return graph.search(graph.build(base, 8, 32, 4), queries, TOP, 32)


def q_graph_full(spark, sf_dir):
    """A beam as wide as a shard: exact wherever the graph is connected."""
    base, queries = sources.split(sources.embeddings(spark, sf_dir))
    return graph.search(graph.build(base, 16, 64, 4), queries, TOP, 4000)


def q_lsh(spark, sf_dir):
    base, queries = sources.split(sources.embeddings(spark, sf_dir))
    return lsh.search(base, queries, TOP, 2.0)


def q_recall_at_k(spark, sf_dir):
    s = Small(spark, sf_dir)
    out = metrics.recall_per_query(s.stage(GUARANTEED), s.truth(), TOP)
    return out.select("query_id", F.round("recall", 6).alias("recall"))


def q_lid(spark, sf_dir):
    out = metrics.lid(Small(spark, sf_dir).truth(20), 20)
    return out.select("query_id", F.round("lid", 4).alias("lid"))


def q_lid_summary(spark, sf_dir):
    out = metrics.lid_summary(metrics.lid(Small(spark, sf_dir).truth(20), 20))
    return out.select(F.round("mean_lid", 3).alias("mean_lid"), F.round("inverse_mean_lid", 3).alias("inverse_mean_lid"), "used", "skipped")


def q_candidate_stats(spark, sf_dir):
    s = Small(spark, sf_dir)
    params = replace(GUARANTEED, min_fraction=0.5)
    out = metrics.summary_stats(s.summary(params, s.stage(params, "activations"), s.assigned()), s.n, TOP)
    return out.select(*[F.round(c, 6).alias(c) for c in ("mean_candidates", "share_of_n", "fallback_share")])


def q_candidate_recall(spark, sf_dir):
    s = Small(spark, sf_dir)
    least = candidates.tau(GUARANTEED.min_fraction, M)
    codes, tables = s.votes(GUARANTEED)
    pairs = scoring.pair_weights(s.truth(), codes, whole.single(tables), K * K).groupBy("query_id", "id").agg(F.sum("weight").alias("score"))
    out = metrics.summary_recall(scoring.summary_of(tables, codes, least, TOP, M, K * K), pairs, least, TOP)
    return out.select(F.round("recall", 6).alias("recall"), "queries")


def q_nearest_found(spark, sf_dir):
    s = Small(spark, sf_dir)
    return metrics.nearest_found(s.stage(GUARANTEED, "candidates"), s.truth()).select(F.round("nn_in_candidates", 6).alias("nn_in_candidates"), "queries")


def _collisions(spark, sf_dir):
    s = Small(spark, sf_dir)
    codes, tables = s.votes(GUARANTEED)
    held = scoring.pair_weights(s.truth(1), codes, whole.single(tables), K * K)
    return held.select("query_id", "subspace", (F.col("weight") > 0).cast("int").alias("hit"))


def q_estimate_p(spark, sf_dir):
    return bounds.estimate_p(_collisions(spark, sf_dir)).select("subspace", F.round("p", 6).alias("p"), "n")


def q_dependence(spark, sf_dir):
    out = bounds.dependence(_collisions(spark, sf_dir))
    return out.select(*[F.round(c, 5).alias(c) for c in ("mean_s", "var_s", "expected_var", "ratio", "mean_phi")])


def q_bounds(spark, sf_dir):
    points = spark.sql("SELECT m, p, m * f AS tau FROM (SELECT explode(array(2,4,8,16,32)) AS m) CROSS JOIN (SELECT explode(array(0.3D,0.5D,0.6D,0.8D,0.95D)) AS p) CROSS JOIN (SELECT explode(array(0.1D,0.25D,0.5D)) AS f)")
    out = bounds.table(points)
    return out.select("m", "p", "tau", *[F.round(c, 6).alias(c) for c in ("hoeffding", "chebyshev", "exact")], "tighter")


def q_required_subspaces(spark, sf_dir):
    points = spark.sql("SELECT p, f, d FROM (SELECT explode(array(0.4D,0.6D,0.8D,0.95D)) AS p) CROSS JOIN (SELECT explode(array(0.1D,0.25D,0.5D)) AS f) CROSS JOIN (SELECT explode(array(0.1D,0.01D,0.001D)) AS d)")
    return points.withColumn("m", F.coalesce(bounds.required_subspaces(F.col("p"), F.col("f"), F.col("d")), F.lit(-1).cast("long")))


def q_bounds_het(spark, sf_dir):
    ps = _collisions(spark, sf_dir).groupBy("subspace").agg(F.avg("hit").alias("p")).agg(F.sort_array(F.collect_list("p")).alias("ps"))
    return ps.select(F.explode(F.array(F.lit(1.0), F.lit(2.0), F.lit(3.0))).alias("tau"), "ps").select("tau", F.round(bounds.hoeffding_het(F.col("ps"), F.col("tau")), 6).alias("bound"))


_RUNS = "VALUES ('a',0.80,10.0,5.0),('a',0.90,8.0,7.0),('a',0.95,5.0,9.0),('b',0.80,12.0,3.0),('b',0.90,8.0,8.0),('b',0.99,1.0,30.0),('c',0.70,20.0,1.0),('c',0.85,9.0,6.0),('c',0.85,9.0,4.0)"


def _runs(spark: SparkSession) -> DataFrame:
    return spark.sql(f"SELECT col1 AS method, CAST(col2 AS DOUBLE) AS recall, CAST(col3 AS DOUBLE) AS qps, CAST(col4 AS DOUBLE) AS build_s FROM {_RUNS}")


def q_pareto(spark, sf_dir):
    return metrics.pareto(_runs(spark), "recall", "qps").select("method", "recall", "qps", "build_s")


def q_min_cost_at(spark, sf_dir):
    return metrics.min_cost_at(_runs(spark), (0.8, 0.85, 0.9, 0.95, 0.99))


def q_speedup_at(spark, sf_dir):
    return metrics.speedup_at(_runs(spark), 0.8).select("method", "qps", F.round("ratio", 6).alias("ratio"))


def q_false_prunes(spark, sf_dir):
    s = Small(spark, sf_dir)
    return metrics.false_prunes(s.stage(replace(OPTIMIZED, patience_factor=None)), s.truth())


def q_quantisation_error(spark, sf_dir):
    s = Small(spark, sf_dir)
    out = metrics.quantisation_error(codebooks.assign(s.base, s.layout, s.books))
    return out.select("subspace", "half", F.round("mse", 6).alias("mse"), "n")


def q_predicted_cost(spark, sf_dir):
    points = spark.sql("SELECT CAST(col1 AS BIGINT) AS n, CAST(col2 AS BIGINT) AS d, 8 AS m, 50 AS k, 16 AS links, CAST(col1 / 100 AS BIGINT) AS candidates FROM VALUES (60000, 784), (90120, 4096), (1000000, 960)")
    out = metrics.predicted_cost(points)
    return out.select("n", "d", *[F.round(c, 3).alias(c) for c in out.columns[4:]])


def q_label_purity(spark, sf_dir):
    """Share of exact neighbours with the query's label."""
    labels = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"), "label")
    base, queries = sources.split(labels)
    near = exact.knn_relational(base, queries, TOP).join(base.select("id", F.col("label").alias("a")), "id")
    near = near.join(queries.select(F.col("id").alias("query_id"), F.col("label").alias("b")), "query_id")
    return near.groupBy("query_id").agg(F.round(F.avg((F.col("a") == F.col("b")).cast("int")), 6).alias("purity"))


def q_filtered_knn(spark, sf_dir):
    labels = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"), "label")
    base, queries = sources.split(labels)
    return filtered_knn(base, queries, 5, F.col("label") == 3)


def q_filtered_knn_post(spark, sf_dir):
    labels = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"), "label")
    base, queries = sources.split(labels)
    return filtered_knn(base, queries, 5, F.col("label") == 3, "post", 20)


def q_filtered_search(spark, sf_dir):
    """Votes among rows of one parity only, with the codebooks of the whole base."""
    s = Small(spark, sf_dir)
    return search_filtered(s.base, s.queries, s.layout, s.books, K, TOP, GUARANTEED, F.col("id") % 2 == 1)


def q_doc_hash_knn(spark, sf_dir):
    """Hashed document vectors (DOC-768): each hundredth id asks all other rows."""
    df = sources.vectors(spark, sf_dir, "DOC-768")
    # One more than asked, as a row may find itself; the nearest 3 others are always among them.
    others = exact.knn(df, df.filter("id % 100 = 0"), 4).filter("query_id != id").select("query_id", "id", "dist2")
    out = exact.merge(others, 3)
    return out.groupBy("query_id").agg(F.round(F.sum("dist2"), 4).alias("sum_dist2"), F.count("*").alias("n"))


def q_doc_knn_join(spark, sf_dir):
    """Nearest other document of every document (DOC-768) through the index, in batches of about 20,000."""
    df = sources.vectors(spark, sf_dir, "DOC-768").persist()  # read by every step of the build and every batch
    index = build_index(df, IndexParams(m=4, k=8, iters=3, shard_rows=2048, policy="never"))
    out = knn_join(index, df, 2, max(2, -(-index.n // 20_000)), SearchParams("guaranteed", 0.1, 0.5))
    return out.filter("query_id != id")


def q_pair_distances(spark, sf_dir):
    """Pairs of one label within a distance, each once."""
    df = load(spark, sf_dir, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("v"))
    a, b = df.alias("a"), df.alias("b")
    pairs = a.join(b, (F.col("a.label") == F.col("b.label")) & (F.col("a.vec_id") < F.col("b.vec_id")))
    d2 = F.round(V.l2sq(F.col("a.v"), F.col("b.v")), 6)
    return pairs.select(F.col("a.vec_id").alias("a_id"), F.col("b.vec_id").alias("b_id"), d2.alias("dist2")).filter("dist2 <= 1.6")


def q_class_means(spark, sf_dir):
    df = load(spark, sf_dir, "embeddings").select("label", F.posexplode("embedding").alias("j", "x"))
    return df.groupBy("label", "j").agg(F.round(F.avg(F.col("x").cast("double")), 6).alias("mean"))


def q_vector_scalars(spark, sf_dir):
    df = sources.embeddings(spark, sf_dir)
    first = F.broadcast(df.filter("id = 0").select(F.col("vec").alias("v")))
    a, b = F.col("vec"), F.col("v")
    return df.crossJoin(first).select(
        "id", F.round(V.l2(a, b), 6).alias("l2"), F.round(V.dot(a, b), 6).alias("dot"), F.round(V.cosine(a, b), 6).alias("cosine"),
        F.round(V.partial_l2sq(a, b, 32), 6).alias("half_l2sq"), F.round(V.norm(V.add(a, b)), 6).alias("norm_sum"), F.round(V.norm(V.sub(a, V.scale(b, 0.5))), 6).alias("norm_mix"),
    )


def q_vector_quality(spark, sf_dir):
    """Good rows and every kind of bad one, counted."""
    df = sources.embeddings(spark, sf_dir).select("vec")
    bad = spark.sql("SELECT CAST(NULL AS ARRAY<DOUBLE>) AS vec UNION ALL SELECT array(1.0D) UNION ALL SELECT array_repeat(CAST('NaN' AS DOUBLE), 64) UNION ALL SELECT array_repeat(CAST('Infinity' AS DOUBLE), 64)")
    return df.unionByName(bad).groupBy(F.coalesce(V.invalid(F.col("vec"), DIM), F.lit("ok")).alias("state")).agg(F.count("*").alias("n"))


def q_event_vectors(spark, sf_dir):
    df = sources.event_profiles(spark, sf_dir)
    return df.select("id", F.aggregate("vec", F.lit(0.0), lambda a, x: a + x).alias("total"), F.round(V.norm(F.col("vec")), 6).alias("norm"))


def q_customer_vectors(spark, sf_dir):
    df = sources.customer_spend(spark, sf_dir)
    return df.select("id", F.round(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x), 2).alias("total"))


def q_variance_layout(spark, sf_dir):
    """Open idea: halves of equal variance on the concentrated view."""
    _, cov = spectral.covariance_matrix(sources.vectors(spark, sf_dir, "E64-decay90"), DIM)
    layout = variance_layout(np.diag(cov), M)
    rows = [(s, h, a, n, float(np.diag(cov)[a : a + n].sum())) for s, h, a, n in layout.halves()]
    return spark.createDataFrame(rows, "subspace int, half int, start int, len int, variance double")


def q_block_rotation(spark, sf_dir):
    """Open idea: only the dimensions that hold 60 % of the variance are rotated."""
    df = sources.vectors(spark, sf_dir, "E64-decay90")
    _, cov = spectral.covariance_matrix(df, DIM)
    dims = rotation.select_block(cov, 0.6)
    out = metrics.variance_spread(rotation.rotate(df, rotation.block(DIM, dims)))
    return out.withColumn("rotated_dims", F.lit(len(dims)))


def q_spread_after_rotation(spark, sf_dir):
    df = sources.vectors(spark, sf_dir, "E64-decay90")
    before = metrics.variance_spread(df).withColumn("state", F.lit("native"))
    after = metrics.variance_spread(rotation.rotate(df, rotation.gaussian_qr(DIM))).withColumn("state", F.lit("rotated"))
    return before.unionByName(after)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, f in globals().items() if name.startswith("q_") and callable(f)}
