"""Vector functions for SQL: Arrow UDFs for bulk work, grouped aggregates, table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType

from subvote.operators.activation import walk


def _rows(s: pd.Series) -> np.ndarray:
    return np.stack(s.to_numpy()).astype(np.float64) if len(s) else np.empty((0, 0))


def l2sq(a: pd.Series, b: pd.Series) -> pd.Series:
    x, y = _rows(a), _rows(b)
    return pd.Series(((x - y) ** 2).sum(axis=1)) if len(a) else pd.Series([], dtype=float)


def dot(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series(np.einsum("ij,ij->i", _rows(a), _rows(b))) if len(a) else pd.Series([], dtype=float)


def mean_vector(v: pd.Series) -> list[float]:
    """Mean of a group's vectors; a grouped aggregate."""
    return _rows(v).mean(axis=0).tolist()


def lid(r: pd.Series) -> float:
    """Local intrinsic dimension of a query's true distances; a grouped aggregate."""
    x = np.sort(r.to_numpy(dtype=float))
    x = x[x > 0]
    logs = np.log(x[-1] / x[:-1]) if len(x) > 1 else np.empty(0)
    return float(1 / logs.mean()) if len(logs) and logs.mean() > 1e-12 else float("nan")


class Traverse:
    """traverse(left distances, right distances, most): cells in ascending cost, lazily."""

    def eval(self, left: list[float], right: list[float], most: int) -> Iterator[tuple[int, int, int, float]]:
        for rank, (i, j, cost) in enumerate(walk(np.array(left), np.array(right)), start=1):
            if rank > most:
                return
            yield rank, i, j, cost


class Nearest:
    """nearest(query, ids, vectors, k): k nearest of a list, for SQL LATERAL."""

    def eval(self, query: list[float], ids: list[int], vectors: list[list[float]], k: int) -> Iterator[tuple[int, int, float]]:
        x = np.array(vectors, dtype=float)
        d2 = np.round(((x - np.array(query)) ** 2).sum(axis=1), 6)
        for rank, i in enumerate(np.lexsort((np.array(ids), d2))[:k], start=1):
            yield rank, int(ids[i]), float(d2[i])


def register(spark: SparkSession) -> None:
    """Make all of them callable from SQL."""
    spark.udf.register("vec_l2sq", F.pandas_udf(l2sq, DoubleType()))
    spark.udf.register("vec_dot", F.pandas_udf(dot, DoubleType()))
    spark.udf.register("vec_mean", F.pandas_udf(mean_vector, ArrayType(DoubleType())))
    spark.udf.register("vec_lid", F.pandas_udf(lid, DoubleType()))
    spark.udtf.register("traverse", F.udtf(Traverse, returnType="rank int, left_code int, right_code int, cost double"))
    spark.udtf.register("nearest", F.udtf(Nearest, returnType="rank int, id long, dist2 double"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sql_l2sq(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, v) -> s + v)")
