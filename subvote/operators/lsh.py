"""Comparator: Spark's own random-projection hashing, re-measured exactly."""

from __future__ import annotations

from pyspark.ml.feature import BucketedRandomProjectionLSH
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subvote.operators.exact import merge


def search(base: DataFrame, queries: DataFrame, k: int, radius: float, bucket: float = 1.0, tables: int = 4, seed: int = 7) -> DataFrame:
    """(query_id, rank, id, dist2) among the pairs that share a bucket within `radius`."""
    b = base.select("id", array_to_vector("vec").alias("features"))
    q = queries.select("id", array_to_vector("vec").alias("features"))
    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=bucket, numHashTables=tables, seed=seed).fit(b)
    pairs = model.approxSimilarityJoin(b, q, radius, distCol="dist")
    return merge(pairs.select(F.col("datasetB.id").alias("query_id"), F.col("datasetA.id").alias("id"), F.round(F.col("dist") * F.col("dist"), 6).alias("dist2")), k)
