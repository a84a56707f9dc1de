"""Packing by shortest-pack-first over the length histogram.

Documents are encoded, closed with an end id and cut into pieces of at most one
sequence.  The histogram of piece lengths (at most `capacity` rows) goes to the driver,
where lengths are placed longest first into the emptiest packing pattern that exists,
moving counts between patterns.  The patterns come back as a bounded table of slots, and
every piece finds its slot by its rank among the pieces of its length.

Defined cases: null text is empty and still has its end id; pieces of one length are
ranked by document id, start and checksum, so ties and repeated rows get slots of their
own; null ids come first; an empty table gives no pieces; other columns are ignored.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subvote.llm._store import materialize
from subvote.llm._text import ragged
from subvote.llm._tokens import id_encoder
from subvote.llm._worker import tidied

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


def cut(docs: DataFrame, vocab_path: str, end_id: int, capacity: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens."""

    @tidied
    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = id_encoder(vocab_path, False)
        for batch in batches:
            for lo, hi, counts, flat in encoder.slices(batch.column(1)):
                sizes = counts + 1
                ids = np.full(int(sizes.sum()), end_id, "<u4")
                ends = np.cumsum(sizes)
                ids[np.repeat(ends - sizes, counts) + ragged(counts)] = flat
                parts = -(-sizes // capacity)
                k = ragged(parts)
                total, begin = np.repeat(sizes, parts), np.repeat(ends - sizes, parts)
                start = k * capacity
                length = np.minimum(total - start, capacity)
                raw = memoryview(ids.tobytes())
                crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip((begin + start).tolist(), (begin + start + length).tolist(), strict=True)]
                doc_ids = batch.column(0).slice(lo, hi - lo).take(pa.array(np.repeat(np.arange(hi - lo), parts)))
                yield pa.RecordBatch.from_arrays([doc_ids, pa.array(start), pa.array(length), pa.array(crc, pa.int64()), pa.array(total)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return docs.select(F.col(id_col).cast("long"), text_col).mapInArrow(encode, PIECES)


def plan_patterns(histogram: dict[int, int], capacity: int) -> list[tuple[int, tuple[int, ...]]]:
    """(count, lengths) of packing patterns that hold every piece of the histogram."""
    patterns: dict[int, list[list]] = {}
    levels: list[int] = []  # heap of the used lengths that have patterns

    def put(used: int, count: int, parts: tuple) -> None:
        if used not in patterns:
            patterns[used] = []
            heapq.heappush(levels, used)
        patterns[used].append([count, parts])

    done: list[tuple[int, tuple[int, ...]]] = []
    for length in sorted(histogram, reverse=True):
        waiting = histogram[length]
        while waiting:
            while levels and not patterns[levels[0]]:
                del patterns[heapq.heappop(levels)]
            if not levels or levels[0] + length > capacity:
                put(length, waiting, (length, None))
                break
            used = levels[0]
            group = patterns[used][-1]
            moved = min(waiting, group[0])
            group[0] -= moved
            waiting -= moved
            if not group[0]:
                patterns[used].pop()
            put(used + length, moved, (length, group[1]))
    for groups in patterns.values():
        for count, parts in groups:
            lengths = []
            while parts is not None:
                lengths.append(parts[0])
                parts = parts[1]
            done.append((count, tuple(reversed(lengths))))
    return sorted(done, key=lambda p: (p[1], p[0]), reverse=True)


def slots(patterns: list[tuple[int, tuple[int, ...]]]) -> np.ndarray:
    """Rows (length, first rank, first sequence, offset), sorted; ranks of a length are dealt in order."""
    out, sequence, next_rank = [], 0, {}
    for count, lengths in patterns:
        offset = 0
        for length in lengths:
            rank = next_rank.get(length, 0)
            out.append((length, rank, sequence, offset))
            next_rank[length] = rank + count
            offset += length
        sequence += count
    return np.array(sorted(out), np.int64).reshape(-1, 4)


def assign(pieces: DataFrame, capacity: int) -> DataFrame:
    """Adds sequence_id and offset to pieces that are read from a table."""
    spark = pieces.sparkSession
    order = [F.col(c).asc_nulls_first() for c in ("length", "doc_id", "start", "ids_crc32")]

    @tidied
    def rank(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[int, int] = {}
        for batch in batches:
            length = batch.column("length").to_numpy()
            if not len(length):
                continue
            edge = np.flatnonzero(np.diff(length, prepend=-1))
            sizes = np.diff(edge, append=len(length))
            base = np.array([seen.get(int(length[e]), 0) for e in edge])
            for e, n in zip(edge, sizes, strict=True):
                seen[int(length[e])] = seen.get(int(length[e]), 0) + int(n)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.repeat(base, sizes) + ragged(sizes))], [*batch.schema.names, "_rank"])

    ranged = pieces.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_part", F.spark_partition_id())
    ranked = materialize(ranged.mapInArrow(rank, f"{PIECES}, _part int, _rank long"), "pack-ranks")
    # One row per task and length of its range: at most tasks + capacity rows.
    runs = ranked.groupBy("length", "_part").agg(F.count("*").alias("n")).collect()
    histogram: dict[int, int] = {}
    bases: dict[tuple[int, int], int] = {}
    for run in sorted(runs, key=lambda r: (r["length"], r["_part"])):
        bases[run["_part"], run["length"]] = histogram.get(run["length"], 0)
        histogram[run["length"]] = histogram.get(run["length"], 0) + run["n"]
    if not histogram:
        return ranked.select(*[c.split()[0] for c in PIECES.split(", ")], F.lit(0).cast("long").alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    table = slots(plan_patterns(histogram, capacity))
    shared = spark.sparkContext.broadcast((table, bases))

    @tidied
    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, bases = shared.value
        keys = (table[:, 0] << 48) | table[:, 1]
        for batch in batches:
            length, part = batch.column("length").to_numpy(), batch.column("_part").to_numpy()
            if not len(length):
                continue
            pair, back = np.unique((part.astype(np.int64) << 32) | length, return_inverse=True)
            base = np.array([bases[int(p >> 32), int(p & 0xFFFFFFFF)] for p in pair])
            total_rank = batch.column("_rank").to_numpy() + base[back]
            at = np.searchsorted(keys, (length << 48) | total_rank, "right") - 1
            sequence = table[at, 2] + total_rank - table[at, 1]
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(sequence), pa.array(table[at, 3])], [*batch.schema.names[:5], "sequence_id", "offset"])

    return ranked.mapInArrow(place, f"{PIECES}, sequence_id long, offset long")


def pack(docs: DataFrame, vocab_path: str, end_id: int = 2, capacity: int = 4096, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces of all documents with their place: PIECES plus sequence_id and offset."""
    return assign(materialize(cut(docs, vocab_path, end_id, capacity, id_col, text_col), "pack-pieces"), capacity)
