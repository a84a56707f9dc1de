"""Baseline: product quantisation, plain or with a learned rotation.

Training alternates a k-means round per slice with an orthogonal Procrustes step: one job
per iteration sums codes, residual error and the cross product of vectors and their
reconstructions; the singular value decomposition is made on the driver.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subvote.operators import codebooks
from subvote.operators.arrow import matrix
from subvote.operators.exact import collect_queries, merge
from subvote.operators.subspaces import Layout


@dataclass
class PqModel:
    layout: Layout
    matrix: np.ndarray
    books: codebooks.Codebooks
    errors: list[float]
    timed_out: bool = False


def slices(dim: int, m: int) -> Layout:
    width, more = divmod(dim, m)
    lengths = [width + (h < more) for h in range(m)]
    starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    return Layout(dim, tuple(int(s) for s in starts), tuple(lengths))


def quantize(x: np.ndarray, layout: Layout, books: codebooks.Codebooks) -> tuple[np.ndarray, np.ndarray]:
    """(codes n x M, reconstruction)."""
    codes = np.stack([codebooks.nearest(x[:, s : s + w], b) for s, w, b in zip(layout.starts, layout.lengths, books, strict=True)], axis=1)
    return codes, np.concatenate([b[codes[:, h]] for h, b in enumerate(books)], axis=1)


def _procrustes(df: DataFrame, layout: Layout, r: np.ndarray, books: codebooks.Codebooks) -> tuple[np.ndarray, float]:
    """Best rotation for the present codes, and the squared error before it."""
    shared = df.sparkSession.sparkContext.broadcast((layout, r, books))

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        layout, r, books = shared.value
        cross, error = np.zeros((layout.dim, layout.dim)), 0.0
        for batch in batches:
            if len(batch):
                x = matrix(batch.column(0)).astype(np.float64)
                _, y = quantize(x @ r, layout, books)
                error += ((x @ r - y) ** 2).sum()
                cross += x.T @ y
        yield pa.RecordBatch.from_pydict({"cross": pa.array([cross.tobytes()], pa.binary()), "error": [error]})

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cross, error = np.zeros((layout.dim, layout.dim)), 0.0
        for batch in batches:
            for raw, e in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                cross, error = cross + np.frombuffer(raw.as_buffer()).reshape(layout.dim, layout.dim), error + e
        yield pa.RecordBatch.from_pydict({"cross": pa.array([cross.tobytes()], pa.binary()), "error": [error]})

    parts = df.select("vec").mapInArrow(local, "cross binary, error double").repartition(8).mapInArrow(add, "cross binary, error double").collect()
    cross = sum(np.frombuffer(bytes(p["cross"])).reshape(layout.dim, layout.dim) for p in parts)
    u, _, vt = np.linalg.svd(cross)
    return u @ vt, float(sum(p["error"] for p in parts))


def train(base: DataFrame, dim: int, m: int, bits: int = 8, iters: int = 20, seed: int = 7, learn: bool = True, timeout_s: float = 3600.0, train_rows: int | None = 100_000, n: int | None = None) -> PqModel:
    """Plain product quantisation with `learn=False`; stops at the time limit with what it has."""
    from subvote.operators.rotation import rotate

    n = base.count() if n is None else n
    if train_rows is not None and n > train_rows:
        base = base.filter(F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << 30)) < F.lit(int(train_rows / n * (1 << 30))))
    base = base.select("id", "vec").persist()
    layout, r, k = slices(dim, m), np.eye(dim), 1 << bits
    books = codebooks.initial(base, layout, k, "hash_sample", seed)
    errors, late, begin = [], False, time.perf_counter()
    for _ in range(iters):
        books, _, error = codebooks.step(rotate(base, r) if learn else base, layout, books)
        errors.append(error)
        if learn:
            r, _ = _procrustes(base, layout, r, books)
        if time.perf_counter() - begin > timeout_s:
            late = True
            break
    base.unpersist()
    return PqModel(layout, r, books, errors, late)


def error(base: DataFrame, model: PqModel) -> float:
    """Mean squared residual of the whole table."""
    _, total = _procrustes(base, model.layout, model.matrix, model.books)
    return total / max(1, base.count())


def search(base: DataFrame, model: PqModel, queries: DataFrame, k: int, rerank: int = 0) -> DataFrame:
    """(query_id, rank, id, dist2) by lookup tables; `rerank` best are measured exactly."""
    ids, q = collect_queries(queries)
    shared = base.sparkSession.sparkContext.broadcast((ids, q, model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q, model = shared.value
        rotated = q @ model.matrix
        tables = [((rotated[:, None, s : s + w] - b[None]) ** 2).sum(axis=2) for s, w, b in zip(model.layout.starts, model.layout.lengths, model.books, strict=True)]
        for batch in batches:
            if not len(batch):
                continue
            names, x = batch.column(0).to_numpy(), matrix(batch.column(1)).astype(np.float64)
            codes, _ = quantize(x @ model.matrix, model.layout, model.books)
            for i, query in enumerate(ids.tolist()):
                d2 = np.round(sum(t[i][codes[:, h]] for h, t in enumerate(tables)), 6)
                best = np.lexsort((names, d2))[: max(k, rerank)]
                if rerank:
                    near = np.round(((x[best] - q[i]) ** 2).sum(axis=1), 6)
                    pick = np.lexsort((names[best], near))[:k]
                    best, values = best[pick], near[pick]
                else:
                    values = d2[best]
                yield pa.RecordBatch.from_arrays([pa.array([query] * len(best)), pa.array(names[best]), pa.array(values)], ["query_id", "id", "dist2"])

    return merge(base.select("id", "vec").mapInArrow(run, "query_id long, id long, dist2 double"), k)
