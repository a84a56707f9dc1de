"""Codebooks of the halves: independent k-means problems, trained together."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subvote.functions.vectors import l2sq, part
from subvote.operators.arrow import matrix
from subvote.operators.subspaces import Layout

Codebooks = list[np.ndarray]  # one K x len matrix per half


def nearest(x: np.ndarray, centroids: np.ndarray) -> np.ndarray:
    """Index of the nearest centroid per row; ties go to the lowest."""
    return np.argmin((centroids * centroids).sum(axis=1)[None] - 2.0 * (x @ centroids.T), axis=1)


def initial(df: DataFrame, layout: Layout, k: int, init: str = "hash_sample", seed: int = 0, n: int | None = None) -> Codebooks:
    """`id_stride`: rows of rank floor(c n / k) by id.  `hash_sample`: k rows of least hash.
    `spread`: seeded farthest-biased draws from a hash sample of 20 k rows."""
    if init == "id_stride":
        n = df.count() if n is None else n
        ranks = [c * n // k + 1 for c in range(k)]
        rows = df.withColumn("r", F.row_number().over(Window.orderBy("id"))).filter(F.col("r").isin(ranks)).collect()
        found = {r["r"]: r["vec"] for r in rows}
        picked = np.array([found[r] for r in ranks], np.float64)
        return [picked[:, s : s + w] for s, w in zip(layout.starts, layout.lengths, strict=True)]
    rows = df.orderBy(F.xxhash64("id", F.lit(seed)), "id").limit(k if init == "hash_sample" else 20 * k).collect()
    x = np.array([r["vec"] for r in rows], np.float64)
    if init == "hash_sample":
        x = x[np.arange(k) % len(x)]
        return [x[:, s : s + w] for s, w in zip(layout.starts, layout.lengths, strict=True)]
    rng, out = np.random.default_rng(seed), []
    for s, w in zip(layout.starts, layout.lengths, strict=True):
        y = x[:, s : s + w]
        centers = [y[rng.integers(len(y))]]
        while len(centers) < k:
            d = ((y[:, None] - np.array(centers)[None]) ** 2).sum(axis=2).min(axis=1)
            centers.append(y[rng.choice(len(y), p=d / d.sum())] if d.sum() > 0 else y[rng.integers(len(y))])
        out.append(np.array(centers))
    return out


def step(df: DataFrame, layout: Layout, books: Codebooks) -> tuple[Codebooks, np.ndarray, float]:
    """One round for all halves in one job: new centroids, counts, squared error before the move.

    A task sends one row per half; empty clusters keep their centroid.
    """
    spark = df.sparkSession
    shared = spark.sparkContext.broadcast((layout, books))
    schema = "half int, n binary, sums binary, error double"

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        layout, books = shared.value
        n = [np.zeros(len(b)) for b in books]
        sums = [np.zeros_like(b) for b in books]
        error = np.zeros(len(books))
        for batch in batches:
            if not len(batch):
                continue
            x = matrix(batch.column(0)).astype(np.float64)
            for h, (s, w, b) in enumerate(zip(layout.starts, layout.lengths, books, strict=True)):
                y = x[:, s : s + w]
                code = nearest(y, b)
                n[h] += np.bincount(code, minlength=len(b))
                onehot = np.zeros((len(y), len(b)))
                onehot[np.arange(len(y)), code] = 1.0
                sums[h] += onehot.T @ y
                error[h] += ((y - b[code]) ** 2).sum()
        yield pa.RecordBatch.from_pydict({"half": pa.array(range(len(books)), pa.int32()), "n": pa.array([a.tobytes() for a in n], pa.binary()), "sums": pa.array([a.tobytes() for a in sums], pa.binary()), "error": error})

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: dict[int, list] = {}
        for batch in batches:
            for h, n, s, e in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2), batch.column(3).to_pylist(), strict=True):
                n, s = np.frombuffer(n.as_buffer()), np.frombuffer(s.as_buffer())
                kept[h] = [kept[h][0] + n, kept[h][1] + s, kept[h][2] + e] if h in kept else [n, s, e]
        for h, (n, s, e) in kept.items():
            yield pa.RecordBatch.from_pydict({"half": pa.array([h], pa.int32()), "n": pa.array([n.tobytes()], pa.binary()), "sums": pa.array([s.tobytes()], pa.binary()), "error": [e]})

    tasks = min(len(books), spark.sparkContext.defaultParallelism)  # a round is short: no more tasks than run at once
    rows = df.select("vec").mapInArrow(local, schema).repartition(tasks, "half").mapInArrow(add, schema).collect()
    out, counts, error = [b.copy() for b in books], [np.zeros(len(b)) for b in books], 0.0
    for r in rows:
        h, n = r["half"], np.frombuffer(bytes(r["n"]))
        sums = np.frombuffer(bytes(r["sums"])).reshape(books[h].shape)
        full = n > 0
        out[h][full] = sums[full] / n[full, None]
        counts[h], error = n, error + r["error"]
    return out, np.array(counts), error


def train(df: DataFrame, layout: Layout, k: int = 50, iters: int = 10, seed: int = 0, init: str = "hash_sample", train_rows: int | None = 100_000, n: int | None = None) -> tuple[Codebooks, list[float]]:
    """Codebooks after `iters` rounds, and the squared error before each round.

    Rounds run over at most about `train_rows` vectors drawn by hash (all with None).
    """
    n = df.count() if n is None else n
    if train_rows is not None and n > train_rows:
        df = df.filter(F.pmod(F.xxhash64("id", F.lit(seed + 1)), F.lit(1 << 30)) < F.lit(int(train_rows / n * (1 << 30))))
    df = df.select("id", "vec").persist() if iters > 1 else df
    books, errors = initial(df, layout, k, init, seed), []
    for _ in range(iters):
        books, _, error = step(df, layout, books)
        errors.append(error)
    if iters > 1:
        df.unpersist()
    return books, errors


def table(spark: SparkSession, layout: Layout, books: Codebooks) -> DataFrame:
    """(subspace, half, code, centroid)."""
    rows = [(h // 2, h % 2, c, [float(v) for v in row]) for h, b in enumerate(books) for c, row in enumerate(b)]
    return spark.createDataFrame(rows, "subspace int, half int, code int, centroid array<double>")


def stride_codebook(df: DataFrame, layout: Layout, k: int) -> DataFrame:
    """The `id_stride` start as a plan: (subspace, half, code, centroid)."""
    ranked = df.withColumn("r", F.row_number().over(Window.orderBy("id")) - 1).withColumn("n", F.count("*").over(Window.partitionBy()))
    codes = df.sparkSession.range(k).select(F.col("id").cast("int").alias("code"))
    picked = ranked.join(F.broadcast(codes), F.expr(f"r = (code * n) div {k}")).select("code", "vec")
    halves = F.broadcast(layout.table(df.sparkSession))
    return picked.crossJoin(halves).select("subspace", "half", "code", part(F.col("vec"), F.col("start"), F.col("len")).alias("centroid"))


def arrays(books: DataFrame, layout: Layout) -> Codebooks:
    """The matrices of a codebook table, which has a row per half and code."""
    rows = sorted(books.select("subspace", "half", "code", "centroid").collect())
    return [np.array([r["centroid"] for r in rows if (r["subspace"], r["half"]) == (h // 2, h % 2)], np.float64) for h in range(2 * layout.m)]


def assign(df: DataFrame, layout: Layout, books: DataFrame) -> DataFrame:
    """(id, subspace, half, code): nearest centroid by a broadcast join; for small tables and checks."""
    halves = layout.table(df.sparkSession).join(books, ["subspace", "half"])
    cut = df.crossJoin(F.broadcast(halves)).select("id", "subspace", "half", "code", l2sq(part(F.col("vec"), F.col("start"), F.col("len")), F.col("centroid")).alias("d2"))
    return cut.groupBy("id", "subspace", "half").agg(F.min(F.struct("d2", "code")).alias("b")).select("id", "subspace", "half", F.col("b.code").alias("code"), F.col("b.d2").alias("d2"))


def lloyd_round(df: DataFrame, layout: Layout, books: DataFrame) -> DataFrame:
    """One round as a plan: means of the assigned slices, empty clusters keep their centroid."""
    halves = F.broadcast(layout.table(df.sparkSession))
    owned = assign(df, layout, books).join(df, "id").join(halves, ["subspace", "half"])
    values = owned.select("subspace", "half", "code", F.posexplode(part(F.col("vec"), F.col("start"), F.col("len"))).alias("j", "x"))
    means = values.groupBy("subspace", "half", "code", "j").agg(F.avg("x").alias("mean"))
    rows = means.groupBy("subspace", "half", "code").agg(F.sort_array(F.collect_list(F.struct("j", "mean"))).alias("c"))
    rows = rows.select("subspace", "half", "code", F.transform("c", lambda s: s["mean"]).alias("moved"))
    return books.join(rows, ["subspace", "half", "code"], "left").select("subspace", "half", "code", F.coalesce("moved", "centroid").alias("centroid"))
