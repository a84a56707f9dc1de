"""Cells of points, their counts, and the inverted layouts."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from subvote.operators.arrow import lists, matrix
from subvote.operators.codebooks import Codebooks, assign, nearest
from subvote.operators.subspaces import Layout


def cells_of(x: np.ndarray, layout: Layout, books: Codebooks) -> np.ndarray:
    """n x M matrix of cells: left code * K + right code."""
    codes = [nearest(x[:, s : s + w], b) for s, w, b in zip(layout.starts, layout.lengths, books, strict=True)]
    return np.stack([codes[2 * m] * len(books[2 * m + 1]) + codes[2 * m + 1] for m in range(layout.m)], axis=1).astype(np.int32)


def encode(df: DataFrame, layout: Layout, books: Codebooks) -> DataFrame:
    """(id, cells array<int>) in Arrow batches; no shuffle."""
    shared = df.sparkSession.sparkContext.broadcast((layout, books))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        layout, books = shared.value
        for batch in batches:
            if len(batch):
                yield pa.RecordBatch.from_arrays([batch.column(0), lists(cells_of(matrix(batch.column(1)).astype(np.float64), layout, books))], ["id", "cells"])

    return df.select("id", "vec").mapInArrow(run, "id long, cells array<int>")


def exact_cells(x: np.ndarray, layout: Layout, books: Codebooks) -> np.ndarray:
    """`cells_of` by plain squared distances, whose ties fall as in `encode_relational`."""
    out = np.zeros((len(x), layout.m), np.int32)
    for lo in range(0, len(x), 1024):
        for h, (s, w, b) in enumerate(zip(layout.starts, layout.lengths, books, strict=True)):
            code = ((x[lo : lo + 1024, s : s + w][:, None] - b[None]) ** 2).sum(axis=2).argmin(axis=1)
            out[lo : lo + 1024, h // 2] += code if h % 2 else code * len(books[h + 1])
    return out


def encode_exact(df: DataFrame, layout: Layout, books: Codebooks) -> DataFrame:
    """(id, cells array<int>): the rows of `encode_relational`, one per id, in Arrow batches."""
    shared = df.sparkSession.sparkContext.broadcast((layout, books))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        layout, books = shared.value
        for batch in batches:
            if len(batch):
                yield pa.RecordBatch.from_arrays([batch.column(0), lists(exact_cells(matrix(batch.column(1)).astype(np.float64), layout, books))], ["id", "cells"])

    return df.filter(F.col("vec").isNotNull()).select("id", "vec").mapInArrow(run, "id long, cells array<int>")


def count_matrix(codes: DataFrame, m: int, k2: int) -> np.ndarray:
    """Ids per subspace and cell, from (id, cells); at most M K^2 rows reach the driver."""
    counts = np.zeros((m, k2), np.int64)
    for r in cell_counts(exploded(codes)).collect():
        counts[r["subspace"], r["cell"]] = r["n"]
    return counts


def encode_relational(df: DataFrame, layout: Layout, books: DataFrame, k: int) -> DataFrame:
    """(id, subspace, cell) as a plan."""
    codes = assign(df, layout, books)
    return codes.groupBy("id", "subspace").agg(
        (F.sum(F.when(F.col("half") == 0, F.col("code") * k).otherwise(F.col("code")))).cast("int").alias("cell")
    )


def exploded(codes: DataFrame) -> DataFrame:
    """(id, subspace, cell) from (id, cells)."""
    return codes.select("id", F.posexplode("cells").alias("subspace", "cell"))


def cell_counts(assignments: DataFrame) -> DataFrame:
    """(subspace, cell, n) of occupied cells."""
    return assignments.groupBy("subspace", "cell").agg(F.count("*").alias("n"))


def map_postings(assignments: DataFrame) -> DataFrame:
    """The fragmented layout: one id list per occupied cell."""
    return assignments.groupBy("subspace", "cell").agg(F.sort_array(F.collect_list("id")).alias("ids"))


def offsets(counts: DataFrame, k: int) -> DataFrame:
    """(subspace, cell, offset) for cells 0..K*K: where the ids of a cell begin in its subspace."""
    spark = counts.sparkSession
    every = counts.select("subspace").distinct().crossJoin(F.broadcast(spark.range(k * k + 1).select(F.col("id").cast("int").alias("cell"))))
    full = every.join(counts, ["subspace", "cell"], "left")
    before = Window.partitionBy("subspace").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    return full.select("subspace", "cell", F.coalesce(F.sum("n").over(before), F.lit(0)).cast("long").alias("offset"))


def positions(assignments: DataFrame) -> DataFrame:
    """(subspace, position, id): ids sorted by cell, then id, as the contiguous layout has them."""
    order = Window.partitionBy("subspace").orderBy("cell", "id")
    return assignments.select("subspace", "cell", "id", (F.row_number().over(order) - 1).cast("long").alias("position"))


def csr(cells: np.ndarray, k2: int) -> tuple[np.ndarray, np.ndarray]:
    """(offsets M x (k2+1), order M x n) of local positions sorted by cell."""
    n, m = cells.shape
    starts, order = np.zeros((m, k2 + 1), np.int32), np.empty((m, n), np.int32)
    for j in range(m):
        order[j] = np.argsort(cells[:, j], kind="stable")
        starts[j, 1:] = np.cumsum(np.bincount(cells[:, j], minlength=k2))
    return starts, order


def sparse_csr(cells: np.ndarray) -> tuple[list[np.ndarray], list[np.ndarray], np.ndarray]:
    """(occupied cells, where each begins and all end, order M x n): as `csr`, without empty cells."""
    n, m = cells.shape
    occupied, starts, order = [], [], np.empty((m, n), np.int32)
    for j in range(m):
        order[j] = np.argsort(cells[:, j], kind="stable")
        found, first = np.unique(cells[order[j], j], return_index=True)
        occupied.append(found.astype(np.int32))
        starts.append(np.append(first, n).astype(np.int32))
    return occupied, starts, order


def pack_ragged(arrays: list[np.ndarray]) -> bytes:
    """Arrays of 32-bit integers as one: how many, their lengths, their values."""
    head = np.array([len(arrays), *(len(a) for a in arrays)], "<i4")
    return b"".join([head.tobytes(), *(a.astype("<i4").tobytes() for a in arrays)])


def read_ragged(raw: bytes) -> list[np.ndarray]:
    whole = np.frombuffer(raw, "<i4")
    sizes = whole[1 : 1 + whole[0]]
    return np.split(whole[1 + whole[0] :], np.cumsum(sizes)[:-1])


def build_postings(codes: DataFrame, k: int, n_shards: int) -> DataFrame:
    """(shard, subspace, offsets, ids): contiguous posting arrays of every shard."""

    def pack(part: pa.Table) -> pa.Table:
        ids = part.column("id").to_numpy()
        order = np.argsort(ids, kind="stable")
        ids, cells = ids[order], matrix(part.column("cells"))[order]
        starts, rows = csr(cells, k * k)
        m = cells.shape[1]
        return pa.table({"shard": pa.array([part.column("shard")[0].as_py()] * m, pa.int32()), "subspace": pa.array(range(m), pa.int32()), "offsets": lists(starts), "ids": lists(ids[rows])})

    shard = F.pmod(F.xxhash64("id"), F.lit(n_shards)).cast("int")
    return codes.withColumn("shard", shard).groupBy("shard").applyInArrow(pack, "shard int, subspace int, offsets array<int>, ids array<long>")


def cell_skew(counts: DataFrame, k: int) -> DataFrame:
    """Per subspace: occupied, empty_share, max_over_mean, gini over occupied cells."""
    order = Window.partitionBy("subspace").orderBy("n", "cell")
    ranked = counts.withColumn("r", F.row_number().over(order))
    out = ranked.groupBy("subspace").agg(
        F.count("*").alias("occupied"), F.max("n").alias("n_max"), F.sum("n").alias("total"), F.sum(F.col("r") * F.col("n")).alias("weighted")
    )
    return out.select(
        "subspace", "occupied", (1 - F.col("occupied") / float(k * k)).alias("empty_share"),
        (F.col("n_max") * F.col("occupied") / F.col("total")).alias("max_over_mean"),
        (2 * F.col("weighted") / (F.col("occupied") * F.col("total")) - (F.col("occupied") + 1) / F.col("occupied")).alias("gini"),
    )
