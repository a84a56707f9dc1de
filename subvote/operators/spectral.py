"""Spectral check: is the variance concentrated enough to rotate the data first?"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subvote.operators.arrow import matrix

THRESHOLD, TOP_SHARE = 0.85, 0.2


@dataclass(frozen=True)
class SpectralReport:
    rows: int
    dim: int
    cev: float
    threshold: float
    policy: str
    rotate: bool
    rank_deficient: bool


def sample_size(n: int, dim: int, rule: str = "guarded", fraction: float = 0.1, cap: int = 100_000) -> int:
    """`paper`: min(fraction n, cap).  `guarded`: at least four rows per dimension, so that a
    small table cannot look concentrated only because its sample has too low a rank."""
    size = min(int(fraction * n), cap)
    return min(n, max(size, 4 * dim)) if rule == "guarded" else max(1, size)


def sample_for_check(df: DataFrame, n: int, dim: int, rule: str = "guarded", fraction: float = 0.1, cap: int = 100_000, seed: int = 0) -> DataFrame:
    """About `sample_size` rows, drawn by the hash of the id: the same rows in every run."""
    share = min(1.0, sample_size(n, dim, rule, fraction, cap) / max(n, 1))
    if share >= 1.0:
        return df
    return df.filter(F.pmod(F.xxhash64(F.col("id"), F.lit(seed)), F.lit(1 << 30)) < F.lit(int(share * (1 << 30))))


def covariance(df: DataFrame) -> DataFrame:
    """(i, j, c) for i <= j from built-in functions; for small dimensions and checks."""
    long = df.select("id", F.posexplode("vec").alias("i", "x"))
    other = df.select("id", F.posexplode("vec").alias("j", "y"))
    return long.join(other, "id").filter("i <= j").groupBy("i", "j").agg(F.covar_samp("x", "y").alias("c"))


def moments(df: DataFrame, dim: int, block: int = 256) -> tuple[int, np.ndarray, np.ndarray]:
    """(rows, sum, Gram matrix), added up in blocks of rows of the matrix.

    Tasks send dim / block rows each; their sums are made on the executors, and the driver
    gets one dim x dim matrix, whatever the number of vectors.
    """
    schema = "block int, n long, sums binary, gram binary"
    cuts = range(0, dim, block)

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total, gram = 0, np.zeros(dim), np.zeros((dim, dim))
        for batch in batches:
            if len(batch):
                x = matrix(batch.column(0)).astype(np.float64)
                n, total = n + len(x), total + x.sum(axis=0)
                gram += x.T @ x
        if n:
            for b, lo in enumerate(cuts):
                yield pa.RecordBatch.from_pydict({"block": pa.array([b], pa.int32()), "n": [n], "sums": pa.array([total.tobytes()], pa.binary()), "gram": pa.array([gram[lo : lo + block].tobytes()], pa.binary())})

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: dict[int, list] = {}
        for batch in batches:
            for b, n, s, g in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), batch.column(3), strict=True):
                s, g = np.frombuffer(s.as_buffer()), np.frombuffer(g.as_buffer())
                kept[b] = [kept[b][0] + n, kept[b][1] + s, kept[b][2] + g] if b in kept else [n, s, g]
        for b, (n, s, g) in kept.items():
            yield pa.RecordBatch.from_pydict({"block": pa.array([b], pa.int32()), "n": [n], "sums": pa.array([s.tobytes()], pa.binary()), "gram": pa.array([g.tobytes()], pa.binary())})

    rows = df.select("vec").mapInArrow(local, schema).repartition(len(cuts), "block").mapInArrow(add, schema).collect()
    if not rows:
        return 0, np.zeros(dim), np.zeros((dim, dim))
    rows = sorted(rows, key=lambda r: r["block"])
    gram = np.concatenate([np.frombuffer(bytes(r["gram"])).reshape(-1, dim) for r in rows])
    return rows[0]["n"], np.frombuffer(bytes(rows[0]["sums"])).copy(), gram


def covariance_matrix(df: DataFrame, dim: int) -> tuple[int, np.ndarray]:
    """(rows, sample covariance) through `moments`."""
    n, total, gram = moments(df, dim)
    if n < 2:
        return n, np.zeros((dim, dim))
    return n, (gram - np.outer(total, total) / n) / (n - 1)


def eigenvalues(cov: np.ndarray) -> np.ndarray:
    """Falling eigenvalues of a covariance matrix, tiny negatives set to 0."""
    return np.maximum(np.linalg.eigvalsh(cov)[::-1], 0.0)


def cev(eigs: np.ndarray, top_share: float = TOP_SHARE) -> float:
    """Share of variance in the first floor(top_share * D) directions."""
    total = float(eigs.sum())
    return float(eigs[: int(top_share * len(eigs))].sum()) / total if total > 0 else 0.0


def decide(value: float, threshold: float = THRESHOLD, policy: str = "adaptive") -> bool:
    """Rotate?  Strictly above the threshold, or by policy `always` / `never`."""
    if policy not in ("adaptive", "always", "never"):
        raise ValueError(f"no policy {policy}")
    return policy == "always" or (policy == "adaptive" and value > threshold)


def check(df: DataFrame, n: int, dim: int, threshold: float = THRESHOLD, policy: str = "adaptive", rule: str = "guarded", top_share: float = TOP_SHARE, seed: int = 0) -> SpectralReport:
    """Sample, covariance, eigenvalues, decision."""
    rows, cov = covariance_matrix(sample_for_check(df, n, dim, rule, seed=seed), dim)
    value = cev(eigenvalues(cov), top_share)
    return SpectralReport(rows, dim, value, threshold, policy, decide(value, threshold, policy), rows <= int(top_share * dim))
