"""Connected components by alternating large and small stars over an edge table.

Every round rewrites edges so that neighbours hang on the smallest node they see; the
rounds end when the table no longer changes, which takes about log(diameter) of them.
Edges stay distributed and each round is written to the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subvote.llm._store import discard, materialize


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """Hang larger (or smaller and own) neighbours of every node on its smallest one."""
    if large:
        around = edges.union(edges.select("v", "u"))
        least = around.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        out = around.join(least, "u").filter(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        least = edges.groupBy("u").agg(F.min("v").alias("m"))
        near = edges.join(least, "u")
        out = near.select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))
    return out.filter("u != v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()


def components(links: DataFrame, name: str = "components") -> DataFrame:
    """(node, root) of every node that is no root, for links (a, b); null ends are left out."""
    edges = links.filter("a != b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    edges = materialize(edges, name)
    before = None
    while True:
        mark = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        if mark == before or not mark[0]:
            return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
        before, old = mark, edges
        edges = materialize(_star(_star(edges, True), False), name)
        discard(old)
