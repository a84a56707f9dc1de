"""Chance that the true nearest neighbour becomes a candidate, as column functions.

M subspaces collide independently with probability p each; the point is a candidate from
`tau` collisions on.  The bounds are conditional on that independence and on p.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def hoeffding(m: Column, p: Column, tau: Column) -> Column:
    """Lower bound by Hoeffding; 0 (nothing claimed) unless M p exceeds tau."""
    gap = m * p - tau
    return F.when(gap > 0, 1.0 - F.exp(-2.0 * gap * gap / m)).otherwise(0.0)


def hoeffding_het(ps: Column, tau: Column) -> Column:
    """The same for a collision probability of its own per subspace."""
    m = F.size(ps)
    gap = F.aggregate(ps, F.lit(0.0), lambda a, x: a + x) - tau
    return F.when(gap > 0, 1.0 - F.exp(-2.0 * gap * gap / m)).otherwise(0.0)


def chebyshev(m: Column, p: Column, tau: Column) -> Column:
    """Lower bound by Chebyshev, not below 0."""
    gap = m * p - tau
    return F.when(gap > 0, F.greatest(F.lit(0.0), 1.0 - m * p * (1.0 - p) / (gap * gap))).otherwise(0.0)


def binomial_tail(m: Column, p: Column, tau: Column) -> Column:
    """Exact P(at least tau of m collide)."""
    log_choose = lambda n, k: F.aggregate(
        F.sequence(F.lit(1), F.greatest(k, F.lit(1))), F.lit(0.0), lambda a, i: a + F.when(i <= k, F.log(n - k + i) - F.log(i)).otherwise(0.0)
    )
    first = F.ceil(tau).cast("int")
    term = lambda s: F.exp(log_choose(m, s)) * F.pow(p, s) * F.pow(1.0 - p, m - s)
    return F.when(first > m, 0.0).otherwise(F.aggregate(F.sequence(first, F.greatest(m.cast("int"), first)), F.lit(0.0), lambda a, s: a + term(s)))


def required_subspaces(p: Column, fraction: Column, delta: Column) -> Column:
    """Least M with failure chance at most delta when tau = fraction * M."""
    return F.when(p > fraction, F.ceil(F.log(1.0 / delta) / (2.0 * F.pow(p - fraction, 2)))).cast("long")


def largest_threshold(m: int, p: float, delta: float) -> float:
    """Largest tau for which the Hoeffding failure bound stays within delta."""
    return m * p - math.sqrt(m * math.log(1.0 / delta) / 2.0)


def table(points: DataFrame) -> DataFrame:
    """All bounds beside the exact tail for rows (m, p, tau)."""
    m, p, tau = F.col("m"), F.col("p"), F.col("tau")
    out = points.withColumn("hoeffding", hoeffding(m, p, tau)).withColumn("chebyshev", chebyshev(m, p, tau))
    out = out.withColumn("exact", binomial_tail(m, p, tau))
    return out.withColumn("tighter", F.when(F.col("hoeffding") >= F.col("chebyshev"), "hoeffding").otherwise("chebyshev"))


def estimate_p(collisions: DataFrame) -> DataFrame:
    """(subspace, p, n) from collision indicators (query_id, subspace, hit) of true neighbours."""
    return collisions.groupBy("subspace").agg(F.avg("hit").alias("p"), F.count("*").alias("n"))


def dependence(collisions: DataFrame) -> DataFrame:
    """Over-dispersion of the collision count and mean pairwise correlation of indicators.

    One row: mean_s, var_s, expected_var (sum of p(1-p)), ratio, mean_phi.
    """
    per_query = collisions.groupBy("query_id").agg(F.sum("hit").alias("s"))
    spread = per_query.agg(F.avg("s").alias("mean_s"), F.var_samp("s").alias("var_s"))
    expected = estimate_p(collisions).agg(F.sum(F.col("p") * (1 - F.col("p"))).alias("expected_var"))
    a = collisions.select("query_id", F.col("subspace").alias("sa"), F.col("hit").cast("double").alias("x"))
    b = collisions.select("query_id", F.col("subspace").alias("sb"), F.col("hit").cast("double").alias("y"))
    pairs = a.join(b, "query_id").filter("sa < sb").groupBy("sa", "sb").agg(F.corr("x", "y").alias("phi"), F.var_pop("x").alias("vx"), F.var_pop("y").alias("vy"))
    phi = pairs.filter("vx > 0 and vy > 0").agg(F.avg("phi").alias("mean_phi"))
    joined = spread.crossJoin(expected).crossJoin(phi)  # three one-row tables
    return joined.withColumn("ratio", F.try_divide("var_s", "expected_var"))
