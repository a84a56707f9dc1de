"""The engine: build an index, answer batches of queries in guaranteed or optimized mode.

Points live in shards.  A shard is one row that holds its vectors, ids, sign bits and the
contiguous postings of every subspace; a query batch meets a shard in one task, votes are
counted in dense arrays there, and only k rows per query and shard leave it.  Activation
uses the cell counts of the whole index, so votes, threshold and candidates do not depend
on how points are spread over shards.
"""

from __future__ import annotations

import json
import math
import time
from collections.abc import Iterator
from dataclasses import asdict, dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subvote.operators import activation, candidates, cells, codebooks, exact, refine, rotation, spectral, whole
from subvote.operators import batch as batched
from subvote.operators.arrow import matrix, sign_words
from subvote.operators.exact import collect_queries
from subvote.operators.subspaces import Layout, uniform_layout

SHARD = "shard int, n long, ids binary, vectors binary, words binary, offsets binary, rows binary"
FORMAT = 2
#: Above this many bytes of activated cells, a search broadcasts their last places instead.
ACTIVE_BYTES = 64 << 20


@dataclass(frozen=True)
class IndexParams:
    m: int = 8
    k: int = 50
    tau_cev: float = spectral.THRESHOLD
    top_share: float = spectral.TOP_SHARE
    policy: str = "adaptive"
    sample_rule: str = "guarded"
    rotation: str = "gaussian"  # or hadamard
    init: str = "hash_sample"
    iters: int = 10
    train_rows: int | None = 100_000
    shard_rows: int = 8192
    storage: str = "f4"  # f8 keeps doubles
    seed: int = 7


@dataclass(frozen=True)
class SearchParams:
    mode: str = "guaranteed"  # or optimized
    ratio: float = 0.06
    min_fraction: float = 0.25
    rank_cut: int | None = None  # k by default
    step: int = refine.STEP
    eps: float = refine.EPSILON
    patience_factor: float | None = refine.PATIENCE
    use_hamming: bool = True
    use_sampling: bool = True
    block: int = 32


@dataclass
class AnnIndex:
    spark: SparkSession
    params: IndexParams
    dim: int
    n: int
    layout: Layout
    books: codebooks.Codebooks
    counts: np.ndarray  # M x K*K over all shards
    shards: DataFrame
    report: spectral.SpectralReport
    matrix: np.ndarray | None = None
    signs: np.ndarray | None = None
    seconds: dict[str, float] = field(default_factory=dict)

    def rotated(self, x: np.ndarray) -> np.ndarray:
        if self.matrix is not None:
            return x @ self.matrix
        return rotation.hadamard(x, self.signs) if self.signs is not None else x


def scale_k(n: int, per_cell: int = 2000) -> int:
    """Centroids per half so that a cell holds about `per_cell` points; 50 for small tables."""
    return max(50, math.ceil(math.sqrt(n / per_cell)))


def build_index(df: DataFrame, params: IndexParams = IndexParams()) -> AnnIndex:
    """Check, rotate if needed, train codebooks, then one fused pass that rotates, encodes,
    packs sign bits and lays out the shards."""
    spark, seconds = df.sparkSession, {}
    clock = time.perf_counter
    begin = clock()
    size = df.agg(F.count("*").alias("n"), F.min(F.size("vec")).alias("lo"), F.max(F.size("vec")).alias("hi")).first()
    n, dim = size["n"], size["lo"] or 0
    if not n:
        raise ValueError("no vectors to index")
    if size["lo"] != size["hi"]:
        raise ValueError("vectors of different lengths; see sources.check")
    report = spectral.check(df, n, dim, params.tau_cev, params.policy, params.sample_rule, params.top_share, params.seed)
    seconds["check"] = clock() - begin

    begin = clock()
    r = signs = None
    inner = df
    if report.rotate:
        if params.rotation == "hadamard":
            signs = rotation.hadamard_signs(dim, params.seed)
        else:
            r = rotation.gaussian_qr(dim, params.seed)
        inner = rotation.rotate(df, r, signs)
    width = dim if signs is None else 1 << max(0, (dim - 1).bit_length())
    layout = uniform_layout(width, params.m)
    seconds["rotation"] = clock() - begin

    begin = clock()
    books, _ = codebooks.train(inner, layout, params.k, params.iters, params.seed, params.init, params.train_rows, n)
    seconds["training"] = clock() - begin

    begin = clock()
    n_shards = max(1, math.ceil(n / params.shard_rows))
    shards = lay_out(df, layout, books, params.k, n_shards, r, signs, params.storage).persist()
    counts = count_cells(shards, layout.m, params.k * params.k)
    seconds["encoding"] = clock() - begin
    return AnnIndex(spark, params, dim, n, layout, books, counts, shards, report, r, signs, seconds)


def shard_of(n_shards: int) -> Column:
    return F.pmod(F.xxhash64("id"), F.lit(n_shards)).cast("int")


def lay_out(df: DataFrame, layout: Layout, books: codebooks.Codebooks, k: int, n_shards: int, r=None, signs=None, storage: str = "f4") -> DataFrame:
    """One row per shard; the only shuffle of vectors in the build.

    Many shards come in partitions for all cores, where their size alone would give one.
    """
    cores = df.sparkSession.sparkContext.defaultParallelism
    shared = df.sparkSession.sparkContext.broadcast((layout, books, r, signs))
    names = [c.split()[0] for c in SHARD.split(", ")]

    def pack(part: pa.Table) -> pa.Table:
        layout, books, r, signs = shared.value
        ids = part.column("id").to_numpy()
        order = np.argsort(ids, kind="stable")
        x = matrix(part.column("vec"))[order].astype(np.float64)
        x = x @ r if r is not None else rotation.hadamard(x, signs) if signs is not None else x
        occupied, starts, rows = cells.sparse_csr(cells.cells_of(x, layout, books))
        values = [ids[order].astype("<i8").tobytes(), x.astype(f"<{storage}").tobytes(), sign_words(x).tobytes(), cells.pack_ragged([*occupied, *starts]), rows.astype("<i4").tobytes()]
        columns = [pa.array([part.column("shard")[0].as_py()], pa.int32()), pa.array([len(ids)], pa.int64())]
        return pa.table([*columns, *[pa.array([v], pa.binary()) for v in values]], names)

    dealt = df.select("id", "vec").withColumn("shard", shard_of(n_shards))
    if n_shards > 4 * cores:
        dealt = dealt.repartition(max(4 * cores, min(n_shards, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))), "shard")
    return dealt.groupBy("shard").applyInArrow(pack, SHARD)


def count_cells(shards: DataFrame, m: int, k2: int) -> np.ndarray:
    """Cell counts over all shards; tasks send one matrix each and executors add them up."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((m, k2), np.int64)
        for batch in batches:
            for raw in batch.column(0):
                parts = cells.read_ragged(raw.as_buffer())
                for j in range(m):
                    total[j, parts[j]] += np.diff(parts[m + j])
        yield pa.RecordBatch.from_pydict({"counts": pa.array([total.tobytes()], pa.binary())})

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((m, k2), np.int64)
        for batch in batches:
            for raw in batch.column(0):
                total += np.frombuffer(raw.as_buffer(), np.int64).reshape(m, k2)
        yield pa.RecordBatch.from_pydict({"counts": pa.array([total.tobytes()], pa.binary())})

    parts = shards.select("offsets").mapInArrow(local, "counts binary").repartition(min(16, shards.sparkSession.sparkContext.defaultParallelism)).mapInArrow(add, "counts binary")
    return sum((np.frombuffer(bytes(r["counts"]), np.int64).reshape(m, k2) for r in parts.collect()), np.zeros((m, k2), np.int64))


def _read(row: dict, dim: int, words: int, m: int, storage: str):
    n = row["n"]
    return (
        np.frombuffer(row["ids"], "<i8"), np.frombuffer(row["vectors"], f"<{storage}").reshape(n, dim), np.frombuffer(row["words"], "<i8").reshape(n, words),
        cells.read_ragged(row["offsets"]), np.frombuffer(row["rows"], "<i4").reshape(m, n),
    )


def shard_votes(offsets: list[np.ndarray], rows: np.ndarray, active: list[np.ndarray] | None, n: int, rank_cut: int, half: list[np.ndarray] | None = None, edge: np.ndarray | None = None) -> np.ndarray:
    """Votes of one query over a shard: contiguous segments of the activated cells.

    Cells come as a list in rank order, or as the places `edge` of the last ones, against
    which the occupied cells of the shard are held.
    """
    score, parts = np.zeros(n, np.int32), len(rows)
    for m in range(parts):
        occupied, starts = offsets[m], offsets[parts + m]
        if active is not None:
            at = np.minimum(np.searchsorted(occupied, active[m]), len(occupied) - 1)
            here = np.flatnonzero(occupied[at] == active[m])
            at, weight = at[here], np.where(here < rank_cut, 2, 1)
        else:
            inside, heavy = activation.up_to(occupied, half[2 * m], half[2 * m + 1], edge[m])
            at = np.flatnonzero(inside)
            weight = np.where(heavy[at], 2, 1)
        lo, size = starts[at], starts[at + 1] - starts[at]
        places = np.repeat(lo - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
        score[rows[m, places]] += np.repeat(weight, size).astype(np.int32)
    return score


def place_edges(index: AnnIndex, q: np.ndarray, limit: int, rank_cut: int) -> np.ndarray:
    """`activation.edges` of a batch of queries, worked out on the executors."""
    shared = index.spark.sparkContext.broadcast((index.layout, index.books, index.counts))
    m, dim = index.layout.m, q.shape[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        layout, books, counts = shared.value
        for batch in batches:
            for i, raw in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                found = activation.edges(np.frombuffer(raw.as_buffer()).reshape(-1, dim), layout, books, counts, limit, rank_cut)
                yield pa.RecordBatch.from_pydict({"first": pa.array([i], pa.int64()), "edges": pa.array([found.tobytes()], pa.binary())})

    step = 16
    rows = [(lo, bytearray(q[lo : lo + step].tobytes())) for lo in range(0, len(q), step)]
    parts = index.spark.createDataFrame(rows, "first long, queries binary").repartition(max(1, len(rows)), "first").mapInArrow(run, "first long, edges binary").collect()
    shared.unpersist()
    return np.concatenate([np.frombuffer(bytes(r["edges"])).reshape(-1, m, 6) for r in sorted(parts, key=lambda r: r["first"])])


RESULT = "kind string, query_id long, id long, score int, dist2 double, n long, dims long, started long"


#: Rows of a task for a block of queries: their candidates, the nearest, and where any lack candidates the best by score.
PACKED = "query_ids binary, n binary, d2 binary, found binary, best_score binary, best_ids binary, best_d2 binary"
#: Queries of a block at most, and pairs of a query and a vector that are met at once.
BLOCK, MET = 1024, 1 << 20


def spread_shards(index: AnnIndex) -> tuple[DataFrame, int]:
    """(shards with a column part, parts): rows dealt to all cores, for a small index comes in one
    partition.  With few shards, a shard goes to several tasks, each with every `parts`-th query:
    small shards to some for every core, so that no core waits for the last one."""
    cores = index.spark.sparkContext.defaultParallelism
    n_shards = max(1, math.ceil(index.n / index.params.shard_rows))
    if n_shards > 4 * cores:
        return index.shards.withColumn("part", F.lit(0)), 1
    rounds = 3 if min(index.n, index.params.shard_rows) * index.dim <= 1 << 20 else 1
    parts = math.ceil(rounds * cores / n_shards)
    split = F.explode(F.array(*[F.lit(i) for i in range(parts)]))
    return index.shards.withColumn("part", split).repartition(n_shards * parts), parts


class _Answers:
    """What a task knows of some queries: the nearest so far, work counters, and the best by score
    of those that lack candidates so far."""

    def __init__(self, ids: np.ndarray, q: np.ndarray, words: np.ndarray, k: int):
        self.ids, self.q, self.words, self.k = ids, q, words, k
        self.nearest = exact.Nearest(ids, q, k)
        shape = (len(ids), k)
        self.d2, self.found = np.full(shape, np.nan), np.full(shape, exact.NO_ID)
        self.count = np.zeros((len(ids), 3), np.int64)  # candidates, dimensions, started
        self.best_score, self.best_ids, self.best_d2 = np.full(shape, -1, np.int32), np.full(shape, exact.NO_ID), np.full(shape, np.nan)
        self.score = np.zeros(shape, np.int32)  # of the nearest, where details are asked for

    def enter(self, rows: np.ndarray, d2: np.ndarray, found: np.ndarray) -> None:
        """More neighbours of some queries, nearest first; no number stands behind the last."""
        here = ~(d2[:, 0] > self.d2[rows, -1])
        rows, d2, found = rows[here], d2[here], found[here]
        if len(rows):
            self.d2[rows], self.found[rows] = exact.least(np.hstack([self.d2[rows], d2]), np.hstack([self.found[rows], found]), self.k)

    def fill(self, rows: np.ndarray, score: np.ndarray, names: np.ndarray, x: np.ndarray) -> None:
        """Best by score, then id, for queries short of candidates in all shards together."""
        n, k = len(names), self.k
        for lo in range(0, len(rows), 256):
            some, got = rows[lo : lo + 256], score[lo : lo + 256].astype(np.int64)
            key = got * n - np.arange(n)
            place = np.argpartition(-key, k - 1, axis=1)[:, :k] if n > k else np.broadcast_to(np.arange(n), got.shape)
            d2 = np.stack([np.round(((x[p] - self.q[i]) ** 2).sum(axis=1), 6) for i, p in zip(some, place, strict=True)])
            wide = [np.hstack(p) for p in ((self.best_score[some], np.take_along_axis(got, place, 1)), (self.best_ids[some], names[place]), (self.best_d2[some], d2))]
            order = np.lexsort((wide[1], -wide[0]), axis=-1)[:, :k]
            self.best_score[some], self.best_ids[some], self.best_d2[some] = (np.take_along_axis(w, order, 1) for w in wide)

    def note_scores(self, names: np.ndarray, rows: np.ndarray, score: np.ndarray) -> None:
        """Keeps the scores of the nearest that are of this shard."""
        _, found = self.all()
        place = np.minimum(np.searchsorted(names, found[rows]), len(names) - 1)
        held = names[place] == found[rows]
        self.score[rows] = np.where(held, np.take_along_axis(score, place, 1), self.score[rows])

    def all(self) -> tuple[np.ndarray, np.ndarray]:
        _, d2, found = self.nearest.rows()
        return exact.least(np.hstack([d2, self.d2]), np.hstack([found, self.found]), self.k)

    def packed(self) -> pa.RecordBatch:
        short = bool((self.count[:, 0] < self.k).any())
        best = [a if short else a[:0] for a in (self.best_score, self.best_ids, self.best_d2)]
        values = [self.ids, self.count[:, 0], *self.all(), *best]
        return pa.RecordBatch.from_arrays([pa.array([np.ascontiguousarray(v).tobytes()], pa.binary()) for v in values], [c.split()[0] for c in PACKED.split(", ")])

    def details(self) -> Iterator[pa.RecordBatch]:
        names = [c.split()[0] for c in RESULT.split(", ")]
        none = pa.nulls(len(self.ids), pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(["count"] * len(self.ids), pa.string()), pa.array(self.ids), none, none.cast(pa.int32()), none.cast(pa.float64()), *map(pa.array, self.count.T.copy())], names)
        d2, found = self.all()
        for kind, score, ids, far in (("near", self.score, found, d2), ("best", self.best_score, self.best_ids, self.best_d2)):
            full = ids != exact.NO_ID
            n = int(full.sum())
            if n:
                zero = pa.array(np.zeros(n, np.int64))
                columns = [np.repeat(self.ids, full.sum(axis=1)), ids[full], score[full], far[full]]
                yield pa.RecordBatch.from_arrays([pa.array([kind] * n, pa.string()), *map(pa.array, columns), zero, zero, zero], names)


def _singly(answers: _Answers, at: np.ndarray, score: np.ndarray, names: np.ndarray, x: np.ndarray, words: np.ndarray, least: int, params: SearchParams, patience: int | None) -> None:
    """Queries one by one, where numbers are too large for the arrays of a shard or ids repeat."""
    k = answers.k
    for i, got in zip(at.tolist(), score, strict=True):
        passed, q = np.flatnonzero(got >= least), answers.q[i]
        if params.mode == "optimized":
            keys = (names[passed], -got[passed].astype(np.int32))
            if params.use_hamming:
                keys = (*keys, np.bitwise_count((words[passed] ^ answers.words[i]).view(np.uint64)).sum(axis=1))
            rows = passed[np.lexsort(keys)]
            best, c, _ = refine.fold(x[rows], names[rows], q, k, params.step, params.eps, patience, params.use_sampling, params.block)
            d2, found, work = np.array([b[0] for b in best]), np.array([b[1] for b in best], np.int64), (len(passed), c.dims, c.started)
        else:
            d2 = np.round(((x[passed] - q) ** 2).sum(axis=1), 6)
            top = np.lexsort((names[passed], d2))[:k]
            d2, found, work = d2[top], names[passed][top], (len(passed), x.shape[1] * len(passed), len(passed))
        rest = (0, k - len(d2))
        answers.count[i] += work
        answers.enter(np.array([i]), np.pad(d2, rest, constant_values=np.nan)[None], np.pad(found, rest, constant_values=exact.NO_ID)[None])


def search(index: AnnIndex, queries: DataFrame, k: int, params: SearchParams = SearchParams(), details: bool = False) -> DataFrame:
    """(query_id, rank, id, dist2) for a batch of queries.

    Guaranteed mode measures every candidate.  Optimized mode weighs votes by cell rank and
    verifies per shard in Hamming order with dimension sampling and patience; patience and
    radius are local to a shard, so work is larger and recall usually no lower than with
    one global order.  A task keeps the nearest of all its shards.  With `details`, rows of
    counters, neighbours and best scores of every task come back instead.
    """
    ids, q = collect_queries(queries)
    q = index.rotated(q)
    optimized = params.mode == "optimized"
    rank_cut = (k if params.rank_cut is None else params.rank_cut) if optimized else 0
    limit = activation.budget(params.ratio, index.n)
    # Small grids: the weight of every cell, or lists of cells, made here.  Else the places of the last ones, from the executors.
    k2 = index.params.k**2
    grid = index.layout.m * k2 * len(q)
    table = active = edges = None
    if grid <= ACTIVE_BYTES:
        table = np.ascontiguousarray(activation.weight_table(q, index.layout, index.books, index.counts, limit, rank_cut).T)
    elif 4 * grid * min(1.0, params.ratio * 4) <= ACTIVE_BYTES:
        active = activation.activate_all(q, index.layout, index.books, index.counts, limit)
    else:
        edges = place_edges(index, q, limit, rank_cut)
    least = candidates.tau(params.min_fraction, index.layout.m)
    dim, m, storage = index.layout.dim, index.layout.m, index.params.storage
    shared = index.spark.sparkContext.broadcast((ids, q, sign_words(q), table, active, edges, (index.layout, index.books) if edges is not None else None))
    patience = None if params.patience_factor is None else math.ceil(params.patience_factor * k)
    shards, parts = spread_shards(index)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q, qw, table, active, edges, codes = shared.value
        met: dict[int, list[tuple[np.ndarray, np.ndarray | None, _Answers]]] = {}

        def scores(at: np.ndarray, offsets: list[np.ndarray], order: np.ndarray) -> np.ndarray:
            out = np.empty((len(at), order.shape[1]), np.int32)
            for line, i in enumerate(at.tolist()):
                half = None if active is not None else [h[0] for h in activation.half_matrix(q[i : i + 1], *codes)]
                out[line] = shard_votes(offsets, order, None if active is None else active[i], order.shape[1], rank_cut, half, None if edges is None else edges[i])
            return out

        for batch in batches:
            for raw in zip(*batch.columns, strict=True):
                row = {name: v.as_py() if pa.types.is_integer(v.type) else v.as_buffer() for name, v in zip(batch.schema.names, raw, strict=True)}
                names, x, words, offsets, order = _read(row, dim, qw.shape[1], m, storage)
                places = batched.vote_places(offsets, order, k2) if table is not None else None
                if row["part"] not in met:
                    mine = np.arange(row["part"], len(ids), parts)
                    cuts = [mine[lo : lo + BLOCK] for lo in range(0, len(mine), BLOCK)]
                    met[row["part"]] = [(at, None if table is None else np.ascontiguousarray(table[:, at]), _Answers(ids[at], q[at], qw[at], k)) for at in cuts]
                shard = batched.Shard(names, x, words, params.step) if optimized else None
                wide = None if optimized else x.astype(np.float64)
                for at, weights, answers in met[row["part"]]:
                    of = lambda some: batched.votes(weights[:, some], places) if weights is not None else scores(at[some], offsets, order)  # noqa: B023, E731
                    every, some = np.arange(len(at)), max(1, MET // len(names))
                    fits = shard is not None and patience != 0 and shard.fits(answers.q)
                    if fits:
                        for rows, d2, place, *work in shard.verify(answers.q, answers.words, of, least, 2 * m, k, params.eps, patience, params.use_hamming, params.use_sampling, params.block):
                            answers.count[rows] += np.stack(work, axis=1)
                            answers.enter(rows, np.where(place < 0, np.nan, d2), np.where(place < 0, exact.NO_ID, names[place]))
                            short = rows[answers.count[rows, 0] < k]
                            if len(short):
                                answers.fill(short, of(short), names, x)
                            if details:
                                answers.note_scores(names, rows, of(rows))
                        continue
                    for lo in range(0, len(at), some):
                        rows = every[lo : lo + some]
                        score = of(rows)
                        passed = score >= least
                        if not optimized and answers.nearest.add(wide, names, passed, rows):
                            n = np.count_nonzero(passed, axis=1)
                            answers.count[rows] += np.stack([n, dim * n, n], axis=1)
                        else:
                            _singly(answers, rows, score, names, x, words, least, params, patience)
                        short = answers.count[rows, 0] < k
                        if short.any():
                            answers.fill(rows[short], score[short], names, x)
                        if details:
                            answers.note_scores(names, rows, score)
        for part in met.values():
            for _, _, answers in part:
                if details:
                    yield from answers.details()
                else:
                    yield answers.packed()

    raw = shards.mapInArrow(run, RESULT if details else PACKED)
    return raw if details else merge_tasks(raw, k)


def merge_tasks(raw: DataFrame, k: int) -> DataFrame:
    """Global top k; a query with fewer than k candidates takes the best k by score instead.

    Shards are searched once: the candidates of a query are counted where its blocks meet.
    """
    types = ("<i8", "<i8", "<f8", "<i8", "<i4", "<i8", "<f8")

    def rows_of(ids: np.ndarray, parts: list[list[np.ndarray]]) -> pa.RecordBatch:
        n = sum(p[0] for p in parts)
        d2, found = exact.least(np.hstack([p[1] for p in parts]), np.hstack([p[2] for p in parts]), k)
        short = np.flatnonzero(n < k)
        if len(short):
            # Too few in all, so too few in every task, which has sent its best then.
            score, names, far = (np.hstack([p[j][short] for p in parts]) for j in (3, 4, 5))
            order = np.lexsort((names, -score), axis=-1)[:, :k]
            d2[short], found[short] = exact.least(np.take_along_axis(far, order, 1), np.take_along_axis(names, order, 1), k)
        full = found != exact.NO_ID
        rank = np.broadcast_to(np.arange(1, k + 1, dtype=np.int32), full.shape)
        return pa.RecordBatch.from_arrays([pa.array(c) for c in (np.repeat(ids, full.sum(axis=1)), rank[full], found[full], d2[full])], ["query_id", "rank", "id", "dist2"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, parts = None, []
        for batch in batches:
            for raw in zip(*batch.columns, strict=True):
                mine = raw[0].as_buffer().to_pybytes()
                if mine != key and parts:
                    yield rows_of(np.frombuffer(key, "<i8"), parts)
                    parts = []
                key = mine
                n, *rest = (np.frombuffer(v.as_buffer(), t) for v, t in zip(raw[1:], types[1:], strict=True))
                parts.append([n, *(a.reshape(-1, k) for a in rest)])
        if parts:
            yield rows_of(np.frombuffer(key, "<i8"), parts)

    return raw.repartition("query_ids").sortWithinPartitions("query_ids").mapInArrow(run, "query_id long, rank int, id long, dist2 double")


def pair_votes(index: AnnIndex, queries: DataFrame, pairs: DataFrame, ratio: float) -> DataFrame:
    """(query_id, id, score) of the given pairs (query_id, id) that got a vote in guaranteed mode.

    The work is that of a search with a threshold of one vote, but only the pairs asked for leave
    the shards.  Pairs go to all shards, like queries.
    """
    ids, q = collect_queries(queries)
    q = index.rotated(q)
    limit = activation.budget(ratio, index.n)
    edges = place_edges(index, q, limit, 0)
    asked = pairs.select("query_id", "id").toArrow()
    at = np.searchsorted(ids, asked.column(0).to_numpy())
    order = np.argsort(at, kind="stable")
    spans = np.searchsorted(at[order], np.arange(len(ids) + 1))
    shared = index.spark.sparkContext.broadcast((ids, q, asked.column(1).to_numpy()[order], spans, edges, index.layout, index.books))
    m = index.layout.m

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q, asked, spans, edges, *codes = shared.value
        for batch in batches:
            for row in batch.to_pylist():
                names = np.frombuffer(row["ids"], "<i8")
                offsets, rows = cells.read_ragged(row["offsets"]), np.frombuffer(row["rows"], "<i4").reshape(m, len(names))
                place = np.minimum(np.searchsorted(names, asked), len(names) - 1)
                held = names[place] == asked
                found: list[tuple[int, np.ndarray, np.ndarray]] = []
                for i in range(len(ids)):
                    here = np.arange(spans[i], spans[i + 1])[held[spans[i] : spans[i + 1]]]
                    if len(here):
                        half = [h[0] for h in activation.half_matrix(q[i : i + 1], *codes)]
                        score = shard_votes(offsets, rows, None, len(names), 0, half, edges[i])[place[here]]
                        found.append((i, asked[here][score > 0], score[score > 0]))
                if found:
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(np.repeat(ids[[f[0] for f in found]], [len(f[1]) for f in found])), pa.array(np.concatenate([f[1] for f in found])), pa.array(np.concatenate([f[2] for f in found]).astype(np.int32))], ["query_id", "id", "score"]
                    )

    return index.shards.select("ids", "offsets", "rows").mapInArrow(run, "query_id long, id long, score int")


def counters(raw: DataFrame) -> DataFrame:
    """(query_id, candidates, dims, started) of a detailed search."""
    return raw.filter("kind = 'count'").groupBy("query_id").agg(F.sum("n").alias("candidates"), F.sum("dims").alias("dims"), F.sum("started").alias("started"))


def search_relational(base: DataFrame, queries: DataFrame, layout: Layout, books: DataFrame, k_cells: int, n: int, k: int, params: SearchParams, stage: str = "result") -> DataFrame:
    """The same search as one declarative plan over small tables.

    `stage` returns an intermediate table: assignments, activations, scores, candidates,
    ordered, result.  Optimized mode keeps one global order per query (the exact order of
    the method); its result comes from `whole.search`, which meets the stages before in dense blocks.
    """
    if stage == "result" and params.mode == "optimized":
        matrices = codebooks.arrays(books, layout)
        counts = cells.count_matrix(cells.encode_exact(base, layout, matrices), layout.m, k_cells * k_cells)
        rank_cut = k if params.rank_cut is None else params.rank_cut
        patience = None if params.patience_factor is None else math.ceil(params.patience_factor * k)
        fixed = (activation.budget(params.ratio, n), rank_cut, candidates.tau(params.min_fraction, layout.m), k, params.step, params.eps, patience)
        return whole.search(base, queries, layout, matrices, counts, *fixed, params.use_hamming, params.use_sampling)
    assigned = cells.encode_relational(base, layout, books, k_cells)
    half = activation.half_distances(queries, layout, books)
    active = activation.traverse_relational(half, cells.cell_counts(assigned), k_cells, activation.budget(params.ratio, n))
    if stage == "activations":
        return active
    optimized = params.mode == "optimized"
    cut = (k if params.rank_cut is None else params.rank_cut) if optimized else 0
    from subvote.operators import scoring

    scores = scoring.rank_weighted(active, assigned, cut)
    if stage == "scores":
        return scores
    chosen = candidates.with_fallback(scores, candidates.tau(params.min_fraction, layout.m), k)
    if stage == "candidates":
        return chosen
    if not optimized:
        return refine.exact(chosen, base, queries, k)
    if params.use_hamming:
        ordered = refine.order_by_hamming(chosen, base, queries, layout.dim)
    else:
        ordered = chosen.withColumn("pos", F.col("rn"))
    return ordered


def filtered_knn(base: DataFrame, queries: DataFrame, k: int, where: Column, strategy: str = "pre", over_fetch: int = 10) -> DataFrame:
    """k-NN among the rows of `base` for which `where` holds (columns of `base`).

    pre: filter, then exact.  post: over-fetch without the filter, then filter; may return
    fewer than k rows.  For votes that only fitting rows receive, see `search_filtered`.
    """
    if strategy == "pre":
        return exact.knn_relational(base.filter(where), queries, k)
    wide = exact.knn_relational(base, queries, k * over_fetch)
    fit = wide.join(base.filter(where).select("id"), "id", "left_semi")
    order = Window.partitionBy("query_id").orderBy("dist2", "id")
    return fit.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "id", "dist2")


def search_filtered(base: DataFrame, queries: DataFrame, layout: Layout, books: DataFrame, k_cells: int, k: int, params: SearchParams, where: Column) -> DataFrame:
    """The relational search in which only rows that fit `where` are counted, vote and are measured;
    codebooks stay those of the whole table, so one index serves every filter."""
    fit = base.filter(where).select("id", "vec")
    return search_relational(fit, queries, layout, books, k_cells, fit.count(), k, params)


def knn_join(index: AnnIndex, left: DataFrame, k: int, batches: int, params: SearchParams = SearchParams()) -> DataFrame:
    """k neighbours for every row of `left`, batch by batch, so that each batch fits a broadcast."""
    out = None
    for b in range(batches):
        part = search(index, left.filter(F.pmod(F.xxhash64("id"), F.lit(batches)) == b), k, params)
        out = part if out is None else out.unionByName(part)
    return out


def save_index(index: AnnIndex, path: str) -> None:
    """Shards as Parquet, everything else (parameters, codebooks, counts, rotation) beside them."""
    spark = index.spark
    index.shards.write.mode("overwrite").parquet(f"{path}/shards")
    meta = {
        "format": FORMAT, "params": asdict(index.params), "dim": index.dim, "n": index.n, "starts": index.layout.starts, "lengths": index.layout.lengths,
        "width": index.layout.dim, "report": asdict(index.report),
    }
    blobs = [("meta", json.dumps(meta).encode()), ("counts", index.counts.astype("<i8").tobytes())]
    blobs += [(f"book-{h}", b.astype("<f8").tobytes()) for h, b in enumerate(index.books)]
    if index.matrix is not None:
        blobs += [(f"rotation-{i}", row.astype("<f8").tobytes()) for i, row in enumerate(index.matrix)]
    if index.signs is not None:
        blobs.append(("signs", index.signs.astype("<f8").tobytes()))
    spark.createDataFrame([(k, bytearray(v)) for k, v in blobs], "name string, value binary").coalesce(1).write.mode("overwrite").parquet(f"{path}/meta")


def load_index(spark: SparkSession, path: str, expect: IndexParams | None = None) -> AnnIndex:
    """Read an index back; with `expect`, its parameters must be those."""
    blobs = {r["name"]: bytes(r["value"]) for r in spark.read.parquet(f"{path}/meta").collect()}
    meta = json.loads(blobs["meta"])
    if meta["format"] != FORMAT:
        raise ValueError(f"index format {meta['format']}, this engine reads {FORMAT}")
    params = IndexParams(**meta["params"])
    if expect is not None and expect != params:
        raise ValueError(f"index was built with {params}")
    layout = Layout(meta["width"], tuple(meta["starts"]), tuple(meta["lengths"]))
    books = [np.frombuffer(blobs[f"book-{h}"]).reshape(params.k, w) for h, w in enumerate(layout.lengths)]
    counts = np.frombuffer(blobs["counts"], np.int64).reshape(layout.m, params.k**2)
    r = np.array([np.frombuffer(blobs[f"rotation-{i}"]) for i in range(meta["dim"])]) if "rotation-0" in blobs else None
    signs = np.frombuffer(blobs["signs"]) if "signs" in blobs else None
    shards = spark.read.schema(SHARD).parquet(f"{path}/shards")
    index = AnnIndex(spark, params, meta["dim"], meta["n"], layout, books, counts, shards, spectral.SpectralReport(**meta["report"]), r, signs)
    return _with_deltas(index, path)


def exists(spark: SparkSession, path: str) -> bool:
    name = spark._jvm.org.apache.hadoop.fs.Path(path)
    return name.getFileSystem(spark._jsc.hadoopConfiguration()).exists(name)


def append_saved(index: AnnIndex, more: DataFrame, path: str, number: int) -> None:
    """New vectors as delta shards of batch `number` beside a saved index.

    A batch that runs again overwrites its own delta, so nothing is lost or added twice.
    """
    n_shards = max(1, math.ceil(more.count() / index.params.shard_rows))
    delta = lay_out(more, index.layout, index.books, index.params.k, n_shards, index.matrix, index.signs, index.params.storage)
    delta.write.mode("overwrite").parquet(f"{path}/deltas/batch={number}")


def _with_deltas(index: AnnIndex, path: str) -> AnnIndex:
    if not exists(index.spark, f"{path}/deltas"):
        return index
    deltas = index.spark.read.schema(SHARD).parquet(f"{path}/deltas").drop("batch")
    n = deltas.agg(F.sum("n")).first()[0] or 0
    counts = index.counts + count_cells(deltas, index.layout.m, index.params.k**2)
    return replace(index, n=index.n + n, counts=counts, shards=index.shards.unionByName(deltas))


def footprint(index: AnnIndex) -> DataFrame:
    """(component, bytes, per_vector, of_raw): stored bytes by component; raw is 4 bytes a value."""
    sums = index.shards.agg(*[F.sum(F.length(c)).alias(c) for c in ("ids", "vectors", "words", "offsets", "rows")]).first().asDict()
    sums["codebooks"] = int(sum(b.nbytes for b in index.books))
    sums["rotation"] = int(index.matrix.nbytes if index.matrix is not None else index.signs.nbytes if index.signs is not None else 0)
    raw = 4 * index.n * index.dim
    rows = [(c, int(b), b / index.n, b / raw) for c, b in sums.items()]
    return index.spark.createDataFrame(rows, "component string, bytes long, per_vector double, of_raw double")


def append(index: AnnIndex, more: DataFrame) -> AnnIndex:
    """New vectors as delta shards, encoded with the frozen codebooks and rotation."""
    n = more.count()
    if not n:
        return index
    first = index.shards.agg(F.max("shard")).first()[0] + 1
    delta = lay_out(more, index.layout, index.books, index.params.k, max(1, math.ceil(n / index.params.shard_rows)), index.matrix, index.signs, index.params.storage)
    delta = delta.withColumn("shard", F.col("shard") + first).persist()
    counts = index.counts + count_cells(delta, index.layout.m, index.params.k**2)
    return replace(index, n=index.n + n, counts=counts, shards=index.shards.unionByName(delta))


def choose(n: int, dim: int, n_queries: int, index: AnnIndex | None, least_work: float = 1e9) -> str:
    """`exact` for small work or without an index, else `index`."""
    return "index" if index is not None and float(n) * dim * n_queries > least_work else "exact"
