"""Exact k-nearest neighbours: the truth of every measure, and the exact class of methods."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from subvote.functions.vectors import l2sq
from subvote.operators.arrow import matrix


#: Vectors of a base block and of a query block at most, and bytes of either.
BASE_ROWS, QUERY_ROWS, BLOCK_BYTES = 4096, 2048, 4 << 20


def blocks(df: DataFrame, name: str, most: int) -> DataFrame:
    """Rows of up to `most` vectors each, as bytes: (`name`_ids, `name`_vecs); no shuffle, null vectors left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        count = 0

        def out(last: bool) -> Iterator[pa.RecordBatch]:
            nonlocal held, count
            ids, x = (np.concatenate(a) for a in zip(*held, strict=True))
            rows = max(1, min(most, BLOCK_BYTES // (8 * max(1, x.shape[1]))))
            end = len(ids) if last else len(ids) // rows * rows
            for lo in range(0, end, rows):
                cut = slice(lo, min(lo + rows, end))
                yield pa.RecordBatch.from_arrays([pa.array([a[cut].tobytes()], pa.binary()) for a in (ids, x)], [f"{name}_ids", f"{name}_vecs"])
            held, count = ([(ids[end:], x[end:])] if end < len(ids) else []), len(ids) - end

        for batch in batches:
            if len(batch):
                held.append((batch.column(0).to_numpy().astype("<i8"), matrix(batch.column(1)).astype("<f8")))
                count += len(batch)
                if count >= most:
                    yield from out(False)
        if count:
            yield from out(True)

    return df.filter(F.col("vec").isNotNull()).select("id", "vec").mapInArrow(run, f"{name}_ids binary, {name}_vecs binary")


def spread(df: DataFrame, share: int = 1) -> DataFrame:
    """Blocks dealt to all cores, as a table in one file is read by one task; beyond those to one
    task for every `share` shuffle partitions."""
    spark = df.sparkSession
    return df.repartition(max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")) // share))


def apart(df: DataFrame, key: str, groups: int) -> DataFrame:
    """Rows dealt by `key` so that its groups, of long work each, meet in tasks of their own as far as
    cores go; dealt by their size, small tables would meet in one."""
    spark = df.sparkSession
    most = max(4 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    return df.repartition(min(most, 8 * groups), key)


def knn_relational(base: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(query_id, rank, id, dist2) as one plan: blocks of vectors joined with the broadcast blocks
    of all queries, the k nearest of every task in packed rows, one merge; nothing passes the driver's Python."""
    pairs = spread(blocks(base, "base", BASE_ROWS), SHARE).crossJoin(F.broadcast(blocks(queries, "query", QUERY_ROWS)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def met() -> Iterator[tuple]:
            for batch in batches:
                for raw in zip(*batch.columns, strict=True):
                    names, x, ids, q = (np.frombuffer(v.as_buffer(), t) for v, t in zip(raw, ("<i8", "<f8", "<i8", "<f8"), strict=True))
                    yield (ids.tobytes(), q.tobytes()), names, x.reshape(len(names), -1), ids, q.reshape(len(ids), -1)

        return packed(met(), k)

    return merge(fold(pairs.mapInArrow(run, PACKED), k), k)


def collect_queries(queries: DataFrame, limit: int = 100_000, most_bytes: int = 1 << 30) -> tuple[np.ndarray, np.ndarray]:
    """(ids, matrix) of a query batch on the driver; batches of more rows or bytes are refused."""
    size = queries.agg(F.count("*").alias("n"), F.sum(F.size("vec").cast("long")).alias("values")).first()
    if size["n"] > limit or 8 * (size["values"] or 0) > most_bytes:
        raise ValueError(f"more than {limit} queries or {most_bytes} bytes in a batch; split it")
    rows = queries.select("id", "vec").toArrow()
    rows = rows.sort_by("id")
    return rows.column(0).to_numpy(), matrix(rows.column(1)).astype(np.float64)


def merge(parts: DataFrame, k: int) -> DataFrame:
    """Best k of partial results (query_id, id, dist2)."""
    order = Window.partitionBy("query_id").orderBy("dist2", "id")
    return parts.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "id", "dist2")


#: Bytes of neighbours that a task holds while it meets more of the base, rough distances that are
#: worked out at once, and bytes of the vectors that are measured at once.
HELD_BYTES, ROUGH, MEASURED_BYTES = 64 << 20, 1 << 20, 1 << 20

#: Every task answers all queries, so tasks beyond the cores are few: one for so many shuffle partitions.
SHARE = 16
#: Queries of a packed row at most, and bytes of its neighbours.
PACKED_ROWS, PACKED_BYTES = 256, 1 << 19
PACKED = "query_ids binary, d2 binary, found binary"
#: Stands, with a distance that is no number, where a query has fewer than k neighbours.
NO_ID = np.iinfo(np.int64).max


def least(d2: np.ndarray, found: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k least by distance, then id, of every line."""
    order = np.lexsort((found, d2), axis=-1)[:, :k]
    return np.take_along_axis(d2, order, 1), np.take_along_axis(found, order, 1)


class Nearest:
    """The k nearest base vectors met so far, for a block of queries.

    All distances are worked out roughly, by one product in single precision where the norms allow;
    what is within the rounding error of the k-th so far is measured again in full.
    """

    def __init__(self, ids: np.ndarray, q: np.ndarray, k: int):
        self.ids, self.q, self.k, self.squares = ids, q, k, (q * q).sum(axis=1)
        self.d2, self.found = np.full((len(q), k), np.inf), np.full((len(q), k), NO_ID)

    def add(self, x: np.ndarray, names: np.ndarray, of: np.ndarray | None = None, asked: np.ndarray | None = None) -> bool:
        """False, with nothing done, where squares leave the range of numbers.  With `of`, queries
        x vectors, only the marked ones count; `asked` are the places of its queries, which follow each other."""
        norms = (x * x).sum(axis=1)
        begin, end = (0, len(self.q)) if asked is None else (int(asked[0]), int(asked[-1]) + 1)
        top = float(norms.max(initial=0.0))
        if not (top < 1e300 and float(self.squares.max(initial=0.0)) < 1e300):
            return False
        # One long vector would blur all others in single precision.
        single = max(top, float(self.squares.max(initial=0.0))) < 1e30 and top <= 64 * float(np.median(norms))
        kind, (n, dim), k = np.dtype("f4" if single else "f8"), x.shape, self.k
        y, a = np.empty((n, dim + 1), kind), np.empty((end - begin, dim + 1), kind)
        y[:, :dim], y[:, dim], a[:, :dim], a[:, dim] = x, norms, -2 * self.q[begin:end], 1
        # Both the k-th and a vector may be off by the error; distances are rounded to 6 places.
        slack = 4 * (dim + 8) * np.finfo(kind).eps * (np.sqrt(top) + np.sqrt(self.squares)) ** 2 + 2e-6
        step, groups = max(1, ROUGH // n), min(n, max(64, 4 * k))
        for lo in range(begin, end, step):
            hi = min(lo + step, end)
            rough = a[lo - begin : hi - begin] @ y.T  # squared distance, less the square of the query
            if of is not None:
                rough[~of[lo - begin : hi - begin]] = np.nan
            kth = self.d2[lo:hi, -1] - self.squares[lo:hi]
            new = np.flatnonzero(np.isinf(kth))
            if len(new) and n >= k:
                # k groups have a member up to the k-th least of their minima.
                tops = rough[new, : n // groups * groups].reshape(len(new), -1, groups)
                tops = tops.min(axis=1) if of is None else np.where(np.isnan(tops), np.inf, tops).min(axis=1)
                kth[new] = np.partition(tops, k - 1, axis=1)[:, k - 1]
            limit = kth + slack[lo:hi]
            at, row = np.divmod(np.flatnonzero(rough <= limit.astype(kind)[:, None]), n)
            if len(at):
                self._enter(lo + at, row, x, names)
        return True

    def _enter(self, at: np.ndarray, row: np.ndarray, x: np.ndarray, names: np.ndarray) -> None:
        d2, some = np.empty(len(at)), max(1, MEASURED_BYTES // (8 * x.shape[1]))
        for lo in range(0, len(at), some):
            gap = x[row[lo : lo + some]]
            gap -= self.q[at[lo : lo + some]]
            gap *= gap
            d2[lo : lo + some] = gap.sum(axis=1)
        d2 = np.round(d2, 6)
        enters = d2 <= self.d2[at, -1]
        at, row, d2 = at[enters], row[enters], d2[enters]
        if not len(at):
            return
        # Queries come in order: a line for each, its k so far and behind them what enters.
        touched, first, line, n = np.unique(at, return_index=True, return_inverse=True, return_counts=True)
        place = self.k + np.arange(len(at)) - first[line]
        wide = np.full((len(touched), self.k + n.max()), np.inf)
        ids = np.full(wide.shape, NO_ID)
        wide[:, : self.k], ids[:, : self.k] = self.d2[touched], self.found[touched]
        wide[line, place], ids[line, place] = d2, names[row]
        self.d2[touched], self.found[touched] = least(wide, ids, self.k)

    def rows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return self.ids, np.where(np.isinf(self.d2), np.nan, self.d2), self.found


def _batch(ids: np.ndarray, d2: np.ndarray, found: np.ndarray) -> pa.RecordBatch:
    full = ~np.isnan(d2) | (found != NO_ID)
    columns = [np.repeat(ids, full.sum(axis=1)), found[full], d2[full]]
    return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["query_id", "id", "dist2"])


def _nearest(met: Iterator[tuple], k: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(query ids, queries x k distances, queries x k ids) of a task, from pairs of blocks (key of the
    query block, base ids, base vectors, query ids, query vectors); query blocks beyond the
    room for them answer pair by pair."""
    held: dict[object, Nearest] = {}
    room = HELD_BYTES
    for key, names, x, ids, q in met:
        best = held.get(key)
        if best is None:
            best = Nearest(ids, q, k)
            size = 16 * k * len(ids) + 2 * q.nbytes
            if size <= room:
                best.ids, best.q = ids.copy(), q.copy()
                held[key], room = best, room - size
        if not best.add(x, names):
            for i, v in enumerate(q):
                d2 = np.round(((x - v) ** 2).sum(axis=1), 6)
                top = np.lexsort((names, d2))[:k]
                rest = (0, k - len(top))
                yield ids[i : i + 1], np.pad(d2[top], rest, constant_values=np.nan)[None], np.pad(names[top], rest, constant_values=NO_ID)[None]
        elif key not in held:
            yield best.rows()
    for best in held.values():
        yield best.rows()


def nearest_of_pairs(met: Iterator[tuple], k: int) -> Iterator[pa.RecordBatch]:
    """(query_id, id, dist2) of the k nearest per query of a task."""
    for part in _nearest(met, k):
        yield _batch(*part)


def packed(met: Iterator[tuple], k: int) -> Iterator[pa.RecordBatch]:
    """`nearest_of_pairs` in rows of up to `PACKED_ROWS` queries, which tasks cut alike."""
    rows = max(1, min(PACKED_ROWS, PACKED_BYTES // (16 * k)))
    for part in _nearest(met, k):
        for lo in range(0, len(part[0]), rows):
            yield pa.RecordBatch.from_arrays([pa.array([np.ascontiguousarray(a[lo : lo + rows]).tobytes()], pa.binary()) for a in part], ["query_ids", "d2", "found"])


def fold(parts: DataFrame, k: int) -> DataFrame:
    """(query_id, id, dist2): the k nearest over the packed rows of the same queries, which meet in one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, best = None, None
        for batch in batches:
            for raw in zip(*batch.columns, strict=True):
                ids, d2, found = (np.frombuffer(v.as_buffer(), t) for v, t in zip(raw, ("<i8", "<f8", "<i8"), strict=True))
                d2, found = d2.reshape(-1, k), found.reshape(-1, k)
                if key == ids.tobytes():
                    best = least(np.hstack([best[0], d2]), np.hstack([best[1], found]), k)
                    continue
                if key is not None:
                    yield _batch(np.frombuffer(key, "<i8"), *best)
                key, best = ids.tobytes(), (d2, found)
        if key is not None:
            yield _batch(np.frombuffer(key, "<i8"), *best)

    return parts.repartition("query_ids").sortWithinPartitions("query_ids").mapInArrow(run, "query_id long, id long, dist2 double")


def knn(base: DataFrame, queries: DataFrame, k: int, block: int = QUERY_ROWS) -> DataFrame:
    """The same result in bulk: the queries pass the driver once, the base is dealt to all cores in blocks."""
    ids, q = collect_queries(queries)
    shared = base.sparkSession.sparkContext.broadcast((ids, q))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q = shared.value

        def met() -> Iterator[tuple]:
            for batch in batches:
                for raw in zip(*batch.columns, strict=True):
                    names, x = np.frombuffer(raw[0].as_buffer(), "<i8"), np.frombuffer(raw[1].as_buffer(), "<f8")
                    for lo in range(0, len(ids), block):
                        yield lo, names, x.reshape(len(names), -1), ids[lo : lo + block], q[lo : lo + block]

        return packed(met(), k)

    return merge(fold(spread(blocks(base, "base", BASE_ROWS), SHARE).mapInArrow(run, PACKED), k), k)


def range_search(base: DataFrame, queries: DataFrame, radius: float) -> DataFrame:
    """(query_id, id, dist2) of all pairs within a distance."""
    q = F.broadcast(queries.select(F.col("id").alias("query_id"), F.col("vec").alias("q")))
    pairs = base.crossJoin(q).select("query_id", "id", F.round(l2sq(F.col("vec"), F.col("q")), 6).alias("dist2"))
    return pairs.filter(F.col("dist2") <= radius * radius)
