"""Baseline: one-bit codes of randomly rotated residuals over k-means clusters.

Each vector is rotated, its residual to the nearest centroid is normalised and kept as D
sign bits, its norm and the product of the residual with its code.  A query probes the
nearest clusters, estimates distances from the bits with an error bound, and measures
exactly what the bound cannot rule out.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from subvote.operators import codebooks, rotation
from subvote.operators.arrow import matrix
from subvote.operators.exact import apart, collect_queries, merge
from subvote.operators.subspaces import Layout

CLUSTER = "cluster int, n long, ids binary, vectors binary, bits binary, norms binary, agree binary"


@dataclass
class OneBitIndex:
    dim: int
    matrix: np.ndarray
    centroids: np.ndarray
    clusters: DataFrame


def codes_of(residual: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bits as bool, residual norms, product of unit residual and unit code)."""
    norms = np.linalg.norm(residual, axis=1)
    bits = residual >= 0
    unit = residual / np.maximum(norms, 1e-12)[:, None]
    agree = np.abs(unit).sum(axis=1) / np.sqrt(residual.shape[1])
    return bits, norms, agree


def estimate(bits: np.ndarray, norms: np.ndarray, agree: np.ndarray, q_res: np.ndarray, eps: float = 1.9) -> tuple[np.ndarray, np.ndarray]:
    """(estimated squared distance, lower bound) of coded residuals to a query's residual.

    <unit, q> is estimated by <code, q> / <code, unit>, which is unbiased over rotations;
    its error shrinks with the square root of the dimension.
    """
    dim = bits.shape[1]
    q_norm = np.linalg.norm(q_res)
    unit_q = q_res / max(q_norm, 1e-12)
    product = ((2.0 * bits - 1.0) @ unit_q) / np.sqrt(dim)
    safe = np.maximum(agree, 1e-12)
    cosine = product / safe
    error = np.sqrt(np.maximum(1.0 - safe**2, 0.0)) / safe * eps / np.sqrt(max(dim - 1, 1))
    base = norms**2 + q_norm**2
    return base - 2 * norms * q_norm * cosine, base - 2 * norms * q_norm * (cosine + error)


def build(base: DataFrame, dim: int, n_list: int = 32, iters: int = 10, seed: int = 7, n: int | None = None) -> OneBitIndex:
    r = rotation.gaussian_qr(dim, seed)
    inner = rotation.rotate(base, r)
    books, _ = codebooks.train(inner, Layout(dim, (0,), (dim,)), n_list, iters, seed, n=n)
    centroids = books[0]
    shared = base.sparkSession.sparkContext.broadcast(centroids)
    names = [c.split()[0] for c in CLUSTER.split(", ")]

    def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if len(batch):
                code = codebooks.nearest(matrix(batch.column(1)), shared.value)
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(code.astype(np.int32))], ["id", "vec", "cluster"])

    def pack(part: pa.Table) -> pa.Table:
        c = part.column("cluster")[0].as_py()
        ids, x = part.column("id").to_numpy(), matrix(part.column("vec")).astype(np.float64)
        order = np.argsort(ids, kind="stable")
        bits, norms, agree = codes_of(x[order] - shared.value[c])
        values = [ids[order].astype("<i8"), x[order].astype("<f8"), np.packbits(bits, axis=1), norms, agree]
        return pa.table([pa.array([c], pa.int32()), pa.array([len(ids)], pa.int64()), *[pa.array([v.tobytes()], pa.binary()) for v in values]], names)

    labelled = inner.mapInArrow(label, "id long, vec array<double>, cluster int")
    return OneBitIndex(dim, r, centroids, apart(labelled, "cluster", n_list).groupBy("cluster").applyInArrow(pack, CLUSTER).persist())


def search(index: OneBitIndex, queries: DataFrame, k: int, n_probe: int, eps: float = 1.9) -> DataFrame:
    """(query_id, rank, id, dist2); every cluster is one task's row, k rows per query leave it."""
    ids, q = collect_queries(queries)
    q = q @ index.matrix
    far = ((q[:, None] - index.centroids[None]) ** 2).sum(axis=2)
    probe = np.argsort(far, axis=1, kind="stable")[:, :n_probe]
    shared = queries.sparkSession.sparkContext.broadcast((ids, q, probe, index.centroids))
    dim = index.dim

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q, probe, centroids = shared.value
        for batch in batches:
            for row in batch.to_pylist():
                asked = np.flatnonzero((probe == row["cluster"]).any(axis=1))
                names, x = np.frombuffer(row["ids"], "<i8"), np.frombuffer(row["vectors"]).reshape(-1, dim)
                bits = np.unpackbits(np.frombuffer(row["bits"], np.uint8).reshape(len(x), -1), axis=1)[:, :dim]
                norms, agree = np.frombuffer(row["norms"]), np.frombuffer(row["agree"])
                for i in asked:
                    guess, low = estimate(bits, norms, agree, q[i] - centroids[row["cluster"]], eps)
                    order = np.argsort(guess, kind="stable")
                    head = order[:k]
                    d2 = ((x[head] - q[i]) ** 2).sum(axis=1)
                    radius = d2.max() if len(head) == k else np.inf
                    rest = order[k:][low[order[k:]] < radius]
                    found = np.concatenate([head, rest])
                    d2 = np.round(np.concatenate([d2, ((x[rest] - q[i]) ** 2).sum(axis=1)]), 6)
                    best = np.lexsort((names[found], d2))[:k]
                    yield pa.RecordBatch.from_arrays([pa.array([int(ids[i])] * len(best)), pa.array(names[found][best]), pa.array(d2[best])], ["query_id", "id", "dist2"])

    return merge(index.clusters.mapInArrow(run, "query_id long, id long, dist2 double"), k)
