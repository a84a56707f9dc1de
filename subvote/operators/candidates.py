"""From scores to candidates: threshold, fallback, and the best share."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def tau(min_fraction: float, m: int) -> int:
    """Least score of a candidate."""
    return max(1, math.ceil(min_fraction * m - 1e-9))


def threshold(scores: DataFrame, least: int) -> DataFrame:
    return scores.filter(F.col("score") >= least)


def with_fallback(scores: DataFrame, least: int, k: int) -> DataFrame:
    """(query_id, id, score, rn, fallback): ids from `least` votes on, or the best k if those are fewer."""
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "id")
    ranked = scores.withColumn("rn", F.row_number().over(order))
    passed = F.col("score") >= least
    return ranked.filter(passed | (F.col("rn") <= k)).withColumn("fallback", ~passed)


def pad(candidates: DataFrame, base: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """Ids without any vote, smallest first, for queries that still have fewer than k candidates."""
    have = candidates.groupBy("query_id").agg(F.count("*").alias("have"))
    short = queries.select(F.col("id").alias("query_id")).join(have, "query_id", "left").withColumn("have", F.coalesce("have", F.lit(0))).filter(F.col("have") < k)
    # At most k + (candidates of a short query) < 2 k smallest ids are needed per query.
    least = base.select("id").orderBy("id").limit(2 * k)
    free = short.crossJoin(F.broadcast(least)).join(candidates.select("query_id", "id"), ["query_id", "id"], "left_anti")
    free = free.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy("id"))).filter(F.col("r") <= k - F.col("have"))
    more = free.select("query_id", "id", F.lit(0).cast("long").alias("score"), (F.col("have") + F.col("r")).cast("int").alias("rn"), F.lit(True).alias("fallback"))
    return candidates.unionByName(more)


def top_fraction(scores: DataFrame, beta: float, n: int) -> DataFrame:
    """The best beta * n ids per query by score."""
    keep = max(1, math.ceil(beta * n - 1e-9))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "id")
    return scores.withColumn("rn", F.row_number().over(order)).filter(F.col("rn") <= keep)
