"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence
from statistics import median

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def hits(result: DataFrame, truth: DataFrame) -> DataFrame:
    """(query_id, id, hit) for every true neighbour."""
    found = result.select("query_id", "id", F.lit(1).alias("found"))
    return truth.select("query_id", "id").join(found, ["query_id", "id"], "left").select("query_id", "id", F.coalesce("found", F.lit(0)).alias("hit"))


def recall_per_query(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(query_id, recall): returned true neighbours over k."""
    return hits(result, truth).groupBy("query_id").agg((F.sum("hit") / F.lit(float(k))).alias("recall"))


def recall(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    return recall_per_query(result, truth, k).agg(F.avg("recall").alias("recall"), F.count("*").alias("queries"))


def timed(plan: Callable[[], DataFrame], runs: int = 3, warm: bool = True) -> tuple[float, list[float]]:
    """Median and all wall seconds of a plan written to nowhere, after one warm run."""
    if warm:
        plan().write.format("noop").mode("overwrite").save()
    seconds = []
    for _ in range(runs):
        begin = time.perf_counter()
        plan().write.format("noop").mode("overwrite").save()
        seconds.append(time.perf_counter() - begin)
    return median(seconds), seconds


def lid(truth: DataFrame, k: int) -> DataFrame:
    """(query_id, lid): maximum-likelihood local intrinsic dimension from true distances.

    One over the mean of ln(r_k / r_i) for i < k; zero distances are left out, and queries
    whose distances are all equal have none.
    """
    r = truth.filter((F.col("rank") <= k) & (F.col("dist2") > 0)).select("query_id", "rank", F.sqrt("dist2").alias("r"))
    far = r.groupBy("query_id").agg(F.max("r").alias("rk"), F.max("rank").alias("last"))
    logs = r.join(far, "query_id").filter(F.col("rank") < F.col("last")).groupBy("query_id").agg(F.avg(F.log(F.col("rk") / F.col("r"))).alias("mean_log"))
    return logs.select("query_id", F.when(F.col("mean_log") > 1e-12, 1 / F.col("mean_log")).alias("lid"))


def lid_summary(per_query: DataFrame) -> DataFrame:
    return per_query.agg(
        F.avg("lid").alias("mean_lid"), (1 / F.avg(1 / F.col("lid"))).alias("inverse_mean_lid"), F.count("lid").alias("used"), F.sum(F.when(F.col("lid").isNull(), 1).otherwise(0)).alias("skipped")
    )


def pareto(runs: DataFrame, x: str, y: str, y_better: str = "high") -> DataFrame:
    """Rows that no other row beats on both measures; ties in both stay."""
    best = F.max if y_better == "high" else F.min
    # Best y among rows of strictly higher x, and among rows of equal x.
    level = runs.groupBy(x).agg(best(y).alias("_level"))
    level = level.withColumn("_above", best("_level").over(Window.orderBy(F.desc(x)).rowsBetween(Window.unboundedPreceding, -1)))
    joined = runs.join(level, x)
    beaten = F.col("_above") >= F.col(y) if y_better == "high" else F.col("_above") <= F.col(y)
    return joined.filter((F.col(y) == F.col("_level")) & (F.col("_above").isNull() | ~beaten)).drop("_level", "_above")


def min_cost_at(runs: DataFrame, thresholds: Sequence[float], by: str = "method", x: str = "recall", cost: str = "build_s") -> DataFrame:
    """(method, threshold, cost): least cost that reaches each recall; null where none does."""
    spark = runs.sparkSession
    marks = spark.createDataFrame([(float(t),) for t in thresholds], "threshold double")
    every = runs.select(by).distinct().crossJoin(F.broadcast(marks))
    reached = runs.select(F.col(by).alias("_by"), F.col(x).alias("_x"), F.col(cost).alias("_cost"))
    joined = every.join(reached, (F.col(by) == F.col("_by")) & (F.col("_x") >= F.col("threshold")), "left")
    return joined.groupBy(by, "threshold").agg(F.min("_cost").alias("cost"))


def speedup_at(runs: DataFrame, recall_at: float, by: str = "method", x: str = "recall", y: str = "qps") -> DataFrame:
    """(method, qps, ratio): best rate of every method at a recall, over the best of the others' next."""
    best = runs.filter(F.col(x) >= recall_at).groupBy(by).agg(F.max(y).alias(y))
    order = Window.orderBy(F.desc(y), by)
    return best.withColumn("next", F.lead(y).over(order)).withColumn("ratio", F.col(y) / F.col("next")).drop("next")


def candidate_stats(candidates: DataFrame, n: int) -> DataFrame:
    """One row: mean candidates per query, their share of n, share of queries on the fallback."""
    return _candidate_stats(candidates.groupBy("query_id").agg(F.count("*").alias("c"), F.max(F.col("fallback").cast("int")).alias("f")), n)


def _candidate_stats(per: DataFrame, n: int) -> DataFrame:
    return per.agg(F.avg("c").alias("mean_candidates"), (F.avg("c") / F.lit(float(n))).alias("share_of_n"), F.avg("f").alias("fallback_share"))


def summary_stats(summary: DataFrame, n: int, k: int) -> DataFrame:
    """`candidate_stats` from `scoring.summary`, without a row per candidate."""
    fill = F.least(F.lit(k).cast("long"), F.col("scored"))
    return _candidate_stats(summary.select("query_id", F.greatest("passed", fill).alias("c"), (F.col("passed") < fill).cast("int").alias("f")), n)


def candidate_recall(candidates: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    return recall(candidates, truth, k)


def summary_recall(summary: DataFrame, pairs: DataFrame, least: int, k: int) -> DataFrame:
    """`candidate_recall` from `scoring.summary` and the scores of the true pairs (query_id, id, score)."""
    joined = pairs.join(summary.select("query_id", "best"), "query_id", "left")
    inside = (F.col("score") >= least) | F.coalesce(F.exists("best", lambda b: b["id"] == F.col("id")), F.lit(False))
    per = joined.groupBy("query_id").agg((F.sum(inside.cast("int")) / F.lit(float(k))).alias("recall"))
    return per.agg(F.avg("recall").alias("recall"), F.count("*").alias("queries"))


def nearest_found(candidates: DataFrame, truth: DataFrame) -> DataFrame:
    """Share of queries whose true nearest neighbour is a candidate."""
    return hits(candidates, truth.filter("rank = 1")).agg(F.avg("hit").alias("nn_in_candidates"), F.count("*").alias("queries"))


def false_prunes(run: DataFrame, truth: DataFrame) -> DataFrame:
    """Candidates pruned although they belong to the true top k: one row (false_prunes, pruned)."""
    first = run.filter("rank = 1").select("query_id", "pruned", "pruned_near")
    # A true neighbour is among the nearest k of the candidates, so no other pruned id can be one.
    of_query = truth.groupBy("query_id").agg(F.collect_set("id").alias("true"))
    hit = F.size(F.array_intersect("pruned_near", F.coalesce("true", F.array().cast("array<long>"))))
    return first.join(of_query, "query_id", "left").agg(F.coalesce(F.sum(hit), F.lit(0)).cast("long").alias("false_prunes"), F.coalesce(F.sum("pruned"), F.lit(0)).cast("long").alias("pruned"))


def variance_spread(df: DataFrame) -> DataFrame:
    """One row: max / min of the per-dimension variances and their coefficient of variation."""
    per = df.select(F.posexplode("vec").alias("j", "x")).groupBy("j").agg(F.var_samp("x").alias("v"))
    return per.agg(F.max("v").alias("v_max"), F.min("v").alias("v_min"), (F.stddev_samp("v") / F.avg("v")).alias("variation")).withColumn("ratio", F.try_divide("v_max", "v_min"))


def quantisation_error(assigned: DataFrame) -> DataFrame:
    """Mean squared residual per half from (subspace, half, d2)."""
    return assigned.groupBy("subspace", "half").agg(F.avg("d2").alias("mse"), F.count("*").alias("n"))


def collisions(truth: DataFrame, activations: DataFrame, assignments: DataFrame) -> DataFrame:
    """(query_id, subspace, hit): was the true nearest neighbour's cell activated?"""
    nn = truth.filter("rank = 1").select("query_id", "id").join(assignments, "id")
    active = activations.select("query_id", "subspace", "cell", F.lit(1).alias("on"))
    return nn.join(active, ["query_id", "subspace", "cell"], "left").select("query_id", "subspace", F.coalesce("on", F.lit(0)).alias("hit"))


def predicted_cost(points: DataFrame) -> DataFrame:
    """Orders of space, build and query work as numbers, for rows (n, d, m, k, links, candidates)."""
    n, d, m, k = (F.col(c).cast("double") for c in ("n", "d", "m", "k"))
    bits = n * d / 8
    return points.select(
        "n", "d", "m", "k",
        (4 * n * d + 4 * n * m).alias("space_method"),
        (4 * n * d + 4 * n * m + 48 * m * k * k).alias("space_uniform_collision"),
        (4 * n * d + bits + 4 * k * d).alias("space_onebit_ivf"),
        (4 * n * d + 4 * n * F.col("links") * F.log2(n)).alias("space_graph"),
        (n * k * d).alias("build_flat"), (n * k * d + n * d * d).alias("build_rotated"),
        (F.col("candidates") * d).alias("query_verify"),
    )
