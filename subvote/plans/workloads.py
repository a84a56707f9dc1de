"""Experiment workloads: profiles, frontiers, sweeps and ablations on the given tables.

Every workload returns its figures as a table.  Wall seconds on a small local table are
dominated by the latency of jobs; read relations between rows, work counters and bytes.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subvote.functions import bounds
from subvote.operators import candidates, codebooks, exact, graph, learned_pq, metrics, onebit_ivf, spectral, uniform_collision
from subvote.operators.engine import AnnIndex, IndexParams, SearchParams, build_index, counters, footprint, pair_votes, search
from subvote.operators.subspaces import uniform_layout
from subvote.sources import vectors as sources

BUILD = IndexParams(m=16, k=8, iters=8, shard_rows=1024)
GUARANTEED = SearchParams("guaranteed", 0.2, 0.25)
OPTIMIZED = SearchParams("optimized", 0.2, 0.35, rank_cut=10, patience_factor=20)


class Bench:
    """One vector view split into base and queries, with its exact neighbours."""

    def __init__(self, spark: SparkSession, sf_dir: str, code: str, k: int = 10):
        self.spark, self.code, self.k = spark, code, k
        df = sources.vectors(spark, sf_dir, code).persist()
        self.base, self.queries = (x.persist() for x in sources.split(df))
        self.n, self.n_queries = self.base.count(), self.queries.count()
        self.truth = exact.knn(self.base, self.queries, k).persist()

    def recall(self, result: DataFrame) -> float:
        return float(metrics.recall(result, self.truth, self.k).first()["recall"] or 0.0)

    def run(self, plan: Callable[[], DataFrame], runs: int = 2) -> tuple[float, float, float]:
        """(recall, queries per second, milliseconds per query) of a search: warm, median of `runs`."""
        result = plan().persist()
        recall = self.recall(result)
        result.unpersist()
        seconds, _ = metrics.timed(plan, runs, warm=False)  # the recall was the warm run
        return recall, self.n_queries / seconds, 1000 * seconds / self.n_queries

    def build(self, params: IndexParams) -> tuple[AnnIndex, float]:
        begin = time.perf_counter()
        index = build_index(self.base, params)
        return index, time.perf_counter() - begin


def profile(spark: SparkSession, sf_dir: str, codes: Sequence[str] = ("E64", "E64-decay90", "E64-mix", "EVT-120", "CUST-P", "DOC-768", "PAGE-768")) -> DataFrame:
    """Size, dimension, queries, k, intrinsic dimension, spectral check."""
    rows = []
    for code in codes:
        b = Bench(spark, sf_dir, code, 20)
        dim = len(b.base.first()["vec"])
        lid = metrics.lid_summary(metrics.lid(b.truth, 20)).first()
        report = spectral.check(b.base, b.n, dim)
        rows.append((code, b.n, dim, b.n_queries, 20, lid["mean_lid"], lid["inverse_mean_lid"], report.cev, report.rotate))
    return spark.createDataFrame(rows, "view string, n long, dim long, queries long, k long, lid double, lid_inverse double, cev double, rotate boolean")


def grids(spark: SparkSession, sf_dir: str, code: str = "E64", layouts: Sequence[int] = (4, 8, 16), ratios: Sequence[float] = (0.01, 0.06, 0.2, 0.4), fractions: Sequence[float] = (0.15, 0.25, 0.4, 0.6), iters: Sequence[int] = (2, 8)) -> DataFrame:
    """The engine over its own parameters, one row per setting and mode."""
    b, rows = Bench(spark, sf_dir, code), []
    for m in layouts:
        for rounds in iters if m == layouts[0] else iters[-1:]:
            index, seconds = b.build(replace(BUILD, m=m, iters=rounds))
            for ratio in ratios:
                for fraction in fractions if m == layouts[-1] else fractions[1:2]:
                    for mode in ("guaranteed", "optimized"):
                        params = SearchParams(mode, ratio, fraction, rank_cut=10, patience_factor=20 if mode == "optimized" else None)
                        rows.append((mode, m, rounds, ratio, fraction, seconds, *b.run(lambda i=index, p=params: search(i, b.queries, b.k, p), 1)))
    return spark.createDataFrame(rows, "mode string, m long, iters long, ratio double, fraction double, build_s double, recall double, qps double, ms_per_query double")


def methods(spark: SparkSession, sf_dir: str, code: str = "E64", k: int = 10, layouts: Sequence[int] = (8, 16)) -> DataFrame:
    """Build seconds, recall and rate of both modes and all baselines, a few settings each (`grids` has more)."""
    b, rows = Bench(spark, sf_dir, code, k), []
    dim = len(b.base.first()["vec"])
    for m in layouts:
        index, seconds = b.build(replace(BUILD, m=m))
        for ratio in (0.06, 0.2, 0.4):
            for mode, fraction in (("guaranteed", 0.25), ("optimized", 0.35)):
                params = SearchParams(mode, ratio, fraction, rank_cut=10, patience_factor=20 if mode == "optimized" else None)
                rows.append((f"method-{mode}", f"m={m} ratio={ratio}", seconds, *b.run(lambda i=index, p=params: search(i, b.queries, b.k, p))))
    layout = uniform_layout(dim, 16)
    begin = time.perf_counter()
    books, _ = codebooks.train(b.base, layout, 8, 8, n=b.n)
    table = codebooks.table(spark, layout, books)
    postings = uniform_collision.build(b.base, layout, table, 8).persist()
    postings.count()
    seconds = time.perf_counter() - begin
    for beta in (0.02, 0.1):
        rows.append(("uniform-collision", f"beta={beta}", seconds, *b.run(lambda x=beta: uniform_collision.search(b.base, postings, b.queries, layout, table, 8, b.n, b.k, 0.2, x))))
    for n_list in (8, 32):
        begin = time.perf_counter()
        ivf = onebit_ivf.build(b.base, dim, n_list, 5, n=b.n)
        ivf.clusters.count()
        seconds = time.perf_counter() - begin
        for probe in (1, n_list // 4, n_list):
            rows.append(("onebit-ivf", f"lists={n_list} probe={probe}", seconds, *b.run(lambda i=ivf, p=probe: onebit_ivf.search(i, b.queries, b.k, p))))
    begin = time.perf_counter()
    model = learned_pq.train(b.base, dim, 8, bits=5, iters=4, n=b.n)
    seconds = time.perf_counter() - begin
    rows.append(("learned-pq", "m=8 bits=5", seconds, *b.run(lambda: learned_pq.search(b.base, model, b.queries, b.k))))
    begin = time.perf_counter()
    world = graph.build(b.base, 16, 64, 4)
    world.graphs.count()
    seconds = time.perf_counter() - begin
    for ef in (max(32, k), 256):
        rows.append(("graph", f"ef={ef}", seconds, *b.run(lambda e=ef: graph.search(world, b.queries, b.k, e))))
    rows.append(("exact", "", 0.0, *b.run(lambda: exact.knn(b.base, b.queries, b.k))))
    return spark.createDataFrame(rows, "method string, config string, build_s double, recall double, qps double, ms_per_query double")


def build_vs_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Least build time that reaches each recall."""
    return metrics.min_cost_at(methods(spark, sf_dir).persist(), (0.8, 0.85, 0.9, 0.95, 0.99))


def recall_qps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows no other row of their method beats on recall and rate."""
    runs = methods(spark, sf_dir, "E64-decay90").persist()
    out = None
    for name in sorted(r[0] for r in runs.select("method").distinct().collect()):
        part = metrics.pareto(runs.filter(F.col("method") == name), "recall", "qps")
        out = part if out is None else out.unionByName(part)
    return out.select("method", "config", "build_s", "recall", "qps", "ms_per_query")


def high_dimension(spark: SparkSession, sf_dir: str, codes: Sequence[str] = ("DOC-768", "DOC-1024", "PAGE-768", "DOC-3072"), k: int = 100) -> DataFrame:
    """W1, W4, W9 on hashed text of 768 to 3,072 dimensions at k = 100: both modes, uniform collision, exact."""
    rows = []
    for code in codes:
        b = Bench(spark, sf_dir, code, k)
        dim = len(b.base.first()["vec"])
        lid = metrics.lid_summary(metrics.lid(b.truth, k)).first()["mean_lid"]
        index, seconds = b.build(replace(BUILD, m=8))
        add = lambda method, plan: rows.append((code, dim, b.n, float(lid or 0.0), index.report.cev, method, seconds, *b.run(plan, 1)))  # noqa: B023, E731
        for ratio in (0.1, 0.3):
            add(f"guaranteed ratio={ratio}", lambda i=index, r=ratio: search(i, b.queries, k, SearchParams("guaranteed", r, 0.25)))  # noqa: B023
            add(f"optimized ratio={ratio}", lambda i=index, r=ratio: search(i, b.queries, k, SearchParams("optimized", r, 0.25, patience_factor=20)))  # noqa: B023
        add("exact", lambda: exact.knn(b.base, b.queries, k))  # noqa: B023
    return spark.createDataFrame(rows, "view string, dim long, n long, lid double, cev double, method string, build_s double, recall double, qps double, ms_per_query double")


def memory(spark: SparkSession, sf_dir: str, code: str = "E64") -> DataFrame:
    """Stored bytes by component, of the method and of the baselines.

    Uniform collision keeps fragmented postings: per occupied cell a key, a reference to its
    list and the list of 64-bit ids, beside the vectors; the method keeps 32-bit places in
    one array per subspace.
    """
    b = Bench(spark, sf_dir, code)
    dim = len(b.base.first()["vec"])
    index, _ = b.build(BUILD)
    raw = 4.0 * b.n * dim
    rows = [("method", r["component"], float(r["bytes"]), r["bytes"] / raw) for r in footprint(index).collect()]
    postings = uniform_collision.build(b.base, index.layout, codebooks.table(spark, index.layout, index.books), index.params.k)
    held = postings.agg(F.count("*").alias("lists"), F.sum(F.size("ids")).alias("ids")).first()
    uniform = [("vectors", raw), ("ids", 8.0 * held["ids"]), ("cells", 24.0 * held["lists"]), ("codebooks", float(sum(x.nbytes for x in index.books)))]
    rows += [("uniform-collision", c, size, size / raw) for c, size in uniform]
    model = learned_pq.train(b.base, dim, 8, bits=5, iters=2, n=b.n)
    learned = [("codes", 1.0 * b.n * len(model.books)), ("rotation", float(model.matrix.nbytes)), ("codebooks", float(sum(x.nbytes for x in model.books))), ("vectors", raw)]
    rows += [("learned-pq", c, size, size / raw) for c, size in learned]
    ivf = onebit_ivf.build(b.base, dim, 16, 3, n=b.n).clusters
    for c in ("ids", "vectors", "bits", "norms", "agree"):
        size = float(ivf.agg(F.sum(F.length(c))).first()[0])
        rows.append(("onebit-ivf", c, size, size / raw))
    links = float(graph.build(b.base, 16, 64, 4).graphs.agg(F.sum(F.length("graph"))).first()[0])
    rows.append(("graph", "graph", links, links / raw))
    return spark.createDataFrame(rows, "method string, component string, bytes double, of_raw double")


def threshold_sweep(spark: SparkSession, sf_dir: str, thresholds: Sequence[float] = (0.2, 0.5, 0.7, 0.8, 0.85, 0.9, 0.95, 1.01), codes: Sequence[str] = ("E64", "E64-decay93", "E64-decay90", "E64-mix", "DOC-768")) -> DataFrame:
    """Which views rotate at each threshold, and what that does to recall and candidates."""
    rows = []
    for code in codes:
        b, seen = Bench(spark, sf_dir, code), {}
        dim = len(b.base.first()["vec"])
        for tau in thresholds:
            report = spectral.check(b.base, b.n, dim, tau)
            if report.rotate not in seen:  # the index depends on the decision alone
                index, seconds = b.build(replace(BUILD, m=8, policy="always" if report.rotate else "never"))
                params = SearchParams("guaranteed", 0.2, 0.4)
                work = counters(search(index, b.queries, b.k, params, details=True)).agg(F.avg("candidates")).first()[0]
                seen[report.rotate] = (seconds, float(work), *b.run(lambda i=index, p=params: search(i, b.queries, b.k, p)))
            rows.append((code, tau, report.cev, report.rotate, *seen[report.rotate]))
    return spark.createDataFrame(rows, "view string, threshold double, cev double, rotated boolean, build_s double, candidates double, recall double, qps double, ms_per_query double")


def patience_sweep(spark: SparkSession, sf_dir: str, factors: Sequence[float] = (1, 2, 5, 10, 20, 40, 60)) -> DataFrame:
    """Recall and candidates started as patience grows."""
    b = Bench(spark, sf_dir, "E64")
    index, _ = b.build(replace(BUILD, shard_rows=1 << 20))
    rows = []
    for factor in factors:
        params = replace(OPTIMIZED, patience_factor=float(factor), block=1)
        raw = search(index, b.queries, b.k, params, details=True)
        work = counters(raw).agg(F.avg("started").alias("s"), F.avg("dims").alias("d")).first()
        rows.append((float(factor), float(work["s"]), float(work["d"]), *b.run(lambda p=params: search(index, b.queries, b.k, p))))
    return spark.createDataFrame(rows, "factor double, started double, dims double, recall double, qps double, ms_per_query double")


def stage_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Full refinement, without sampling, without Hamming order; patience stays on."""
    rows = []
    for code in ("E64", "E64-decay90"):
        b = Bench(spark, sf_dir, code)
        index, _ = b.build(replace(BUILD, shard_rows=1 << 20))
        for name, change in (("full", {}), ("no sampling", {"use_sampling": False}), ("no hamming", {"use_hamming": False})):
            for step in (8, 32):
                params = replace(OPTIMIZED, patience_factor=2.0, step=step, block=1, **change)
                work = counters(search(index, b.queries, b.k, params, details=True)).agg(F.avg("started").alias("s"), F.avg("dims").alias("d")).first()
                rows.append((code, name, step, float(work["s"]), float(work["d"]), *b.run(lambda p=params: search(index, b.queries, b.k, p))))
    return spark.createDataFrame(rows, "view string, stages string, step long, started double, dims double, recall double, qps double, ms_per_query double")


def bound_check(spark: SparkSession, sf_dir: str, seeds: int = 8) -> DataFrame:
    """Share of queries whose nearest neighbour is a candidate, beside both bounds, over seeds.

    p is the share of subspaces in which queries and nearest neighbours collide, of the same
    index: every row has the bounds of its own setting.
    """
    rows = []
    for code, policy in (("E64", "never"), ("E64-decay90", "never"), ("E64-decay90", "always")):
        b = Bench(spark, sf_dir, code)
        for seed in range(seeds):
            index, _ = b.build(replace(BUILD, m=8, policy=policy, seed=seed + 1, iters=3))
            nearest = b.truth.filter("rank = 1").select("query_id", "id")
            votes = [r["score"] for r in pair_votes(index, b.queries, nearest, 0.2).select("score").collect()]  # one row per query at most
            index.shards.unpersist()
            tau = candidates.tau(0.25, index.layout.m)
            p = sum(votes) / (index.layout.m * b.n_queries)
            rows.append((code, policy, seed, index.layout.m, tau, sum(v >= tau for v in votes) / b.n_queries, len(votes) / b.n_queries, p))
    table = spark.createDataFrame(rows, "view string, policy string, seed long, m long, tau long, nn_found double, nn_touched double, p double")
    point = [F.col(c).cast("double") for c in ("m", "tau")]
    return table.withColumn("hoeffding", bounds.hoeffding(point[0], F.col("p"), point[1])).withColumn("chebyshev", bounds.chebyshev(point[0], F.col("p"), point[1]))


def modes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Guaranteed against optimized mode at equal thresholds."""
    rows = []
    for code in ("E64", "E64-decay90"):
        b = Bench(spark, sf_dir, code)
        index, _ = b.build(BUILD)
        for params in (GUARANTEED, replace(OPTIMIZED, min_fraction=0.25)):
            work = counters(search(index, b.queries, b.k, params, details=True)).agg(F.avg("candidates").alias("c"), F.avg("dims").alias("d")).first()
            rows.append((code, params.mode, float(work["c"]), float(work["d"]), *b.run(lambda p=params: search(index, b.queries, b.k, p))))
    return spark.createDataFrame(rows, "view string, mode string, candidates double, dims double, recall double, qps double, ms_per_query double")


def dimension_scaling(spark: SparkSession, sf_dir: str, dims: Sequence[int] = (64, 256, 1024, 4096), n: int = 2000) -> DataFrame:
    """Seconds by build stage and share of check and rotation as the dimension grows."""
    rows = []
    for dim in dims:
        df = sources.synthetic(spark, n, dim, spectrum=0.999, latent=32, partitions=8).persist()
        base, queries = sources.split(df, 100)
        base = base.persist()
        truth = exact.knn(base, queries, 10).persist()
        for policy in ("never", "always"):
            index = build_index(base, IndexParams(m=8, k=16, iters=3, policy=policy, shard_rows=1024))
            total = sum(index.seconds.values())
            recall = metrics.recall(search(index, queries, 10, SearchParams("guaranteed", 0.05, 0.5)), truth, 10).first()["recall"]
            rows.append((dim, policy, total, index.seconds["check"] / total, index.seconds["encoding"] / total, float(recall)))
    return spark.createDataFrame(rows, "dim long, policy string, build_s double, check_share double, encoding_share double, recall double")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    listed = (profile, build_vs_recall, recall_qps, grids, high_dimension, memory, threshold_sweep, patience_sweep, stage_ablation, bound_check, modes, dimension_scaling)
    return {f"w_{f.__name__}": f for f in listed}
