"""Baseline: uniform collision counting on fragmented postings, never rotated.

A point collects one vote per subspace whose activated cells hold it; the best share of
points by votes is measured exactly.  Postings are id lists per occupied cell.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subvote.operators import activation, candidates, cells, refine, scoring
from subvote.operators.subspaces import Layout


def build(base: DataFrame, layout: Layout, books: DataFrame, k_cells: int) -> DataFrame:
    """(subspace, cell, ids)."""
    return cells.map_postings(cells.encode_relational(base, layout, books, k_cells))


def search(base: DataFrame, postings: DataFrame, queries: DataFrame, layout: Layout, books: DataFrame, k_cells: int, n: int, k: int, ratio: float = 0.05, beta: float = 0.005) -> DataFrame:
    """(query_id, rank, id, dist2)."""
    counts = postings.select("subspace", "cell", F.size("ids").cast("long").alias("n"))
    half = activation.half_distances(queries, layout, books)
    active = activation.traverse_relational(half, counts, k_cells, activation.budget(ratio, n))
    assigned = postings.select("subspace", "cell", F.explode("ids").alias("id"))
    chosen = candidates.top_fraction(scoring.uniform(active, assigned), max(beta, k / n), n)
    return refine.exact(chosen, base, queries, k)
