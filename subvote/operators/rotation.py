"""Orthogonal rotations: dense from a Gaussian matrix, block-wise, and signed Hadamard."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from subvote.operators.arrow import lists, matrix


def gaussian_qr(dim: int, seed: int = 7) -> np.ndarray:
    """Orthogonal factor of a Gaussian matrix; signs fixed so that the law is uniform."""
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((dim, dim)))
    return q * np.sign(np.diag(r))


def hadamard_signs(dim: int, seed: int = 7) -> np.ndarray:
    return np.where(np.random.default_rng(seed).random(dim) < 0.5, -1.0, 1.0)


def hadamard(x: np.ndarray, signs: np.ndarray) -> np.ndarray:
    """Signed Walsh-Hadamard rotation of rows, D log D; pads with zeros to a power of two."""
    size = 1 << max(0, (len(signs) - 1).bit_length())
    out = np.zeros((len(x), size))
    out[:, : x.shape[1]] = x * signs
    step = 1
    while step < size:
        view = out.reshape(len(x), -1, 2, step)
        out = np.stack([view[:, :, 0] + view[:, :, 1], view[:, :, 0] - view[:, :, 1]], axis=2).reshape(len(x), size)
        step *= 2
    return out / np.sqrt(size)


def block(dim: int, dims: np.ndarray, seed: int = 7) -> np.ndarray:
    """Rotates only the listed dimensions and leaves the others as they are."""
    out = np.eye(dim)
    out[np.ix_(dims, dims)] = gaussian_qr(len(dims), seed)
    return out


def select_block(cov: np.ndarray, share: float) -> np.ndarray:
    """Fewest dimensions, by variance, that hold a share of the total."""
    variance = np.diag(cov)
    order = np.argsort(-variance, kind="stable")
    need = np.searchsorted(np.cumsum(variance[order]), share * variance.sum()) + 1
    return np.sort(order[:need])


def rotate(df: DataFrame, r: np.ndarray | None = None, signs: np.ndarray | None = None) -> DataFrame:
    """(id, vec) times the matrix, or by the signed Hadamard rotation; no shuffle."""
    shared = df.sparkSession.sparkContext.broadcast((r, signs))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r, signs = shared.value
        for batch in batches:
            if len(batch):
                x = matrix(batch.column(1)).astype(np.float64)
                yield pa.RecordBatch.from_arrays([batch.column(0), lists(x @ r if r is not None else hadamard(x, signs))], ["id", "vec"])

    return df.select("id", "vec").mapInArrow(run, "id long, vec array<double>")
