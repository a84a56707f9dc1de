"""Cutting dimensions into subspaces of two halves each."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class Layout:
    """Halves in order: half h covers [starts[h], starts[h] + lengths[h]); subspace m has halves 2m, 2m+1."""

    dim: int
    starts: tuple[int, ...]
    lengths: tuple[int, ...]

    @property
    def m(self) -> int:
        return len(self.starts) // 2

    def halves(self) -> list[tuple[int, int, int, int]]:
        """(subspace, half, start, len)."""
        return [(h // 2, h % 2, s, n) for h, (s, n) in enumerate(zip(self.starts, self.lengths, strict=True))]

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.halves(), "subspace int, half int, start int, len int")


def _of_lengths(dim: int, lengths: list[int]) -> Layout:
    if min(lengths) < 1:
        raise ValueError("a half needs at least one dimension")
    starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    return Layout(dim, tuple(int(s) for s in starts), tuple(lengths))


def uniform_layout(dim: int, m: int) -> Layout:
    """M equal subspaces of two equal halves; what does not divide widens the first halves."""
    width, more = divmod(dim, 2 * m)
    return _of_lengths(dim, [width + (h < more) for h in range(2 * m)])


def variance_layout(variances: np.ndarray, m: int) -> Layout:
    """Contiguous halves of about equal variance instead of equal width."""
    dim, goal = len(variances), variances.sum() / (2 * m)
    lengths, at = [], 0
    for h in range(2 * m):
        left = 2 * m - h - 1
        end, held = at + 1, variances[at]
        while end < dim - left and held + variances[end] / 2 <= goal:
            held += variances[end]
            end += 1
        if left == 0:
            end = dim
        lengths.append(end - at)
        at = end
    return _of_lengths(dim, lengths)
