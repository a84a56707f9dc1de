"""Token-id files: one independent zstandard frame per document and a trailing seek table.

A shard file is

    frame 0 .. frame n-1   ids of one document each, little-endian unsigned 32-bit
    frame n                directory: the n document ids as signed 64-bit, then n null flags
    seek table             skippable frame of the zstd seekable format: per frame its
                           compressed size, size and checksum (low 32 bits of xxh64 of
                           the decompressed bytes), then frame count, flags and magic

so any zstd tool can read the whole file and a reader that wants some documents
(`fetch_documents`) reads the footer, the directory and only their frames.

Shards hold ranges of ascending ids.  A task writes its shard under a name of its own
attempt and then renames it, so lost executors and second attempts leave whole files.

Defined cases: null text is empty and encodes to the end id alone; null ids come first;
rows that repeat an id (or have none) are ordered by the digest of their text and may lie
in several shards; an empty table writes no shard; other
columns are ignored.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from subvote.llm._store import delete, list_names, materialize, new_path, text_tag
from subvote.llm._text import ragged
from subvote.llm._tokens import id_encoder
from subvote.llm._worker import tidied

# Fixed values of the zstd seekable format.
SKIPPABLE_MAGIC = 0x184D2A5E
SEEKABLE_MAGIC = 0x8F92EAB1
CHECKSUM_FLAG = 0x80


class ShardWriter:
    """Writes frames to a binary stream and the seek table at the end."""

    def __init__(self, out, level: int = 3):
        self.out, self.entries, self.ids = out, [], []
        self.compress = zstandard.ZstdCompressor(level=level, write_checksum=False, write_content_size=True).compress

    def _frame(self, data: bytes) -> None:
        packed = self.compress(data)
        self.out.write(packed)
        self.entries.append(struct.pack("<III", len(packed), len(data), xxhash.xxh64_intdigest(data) & 0xFFFFFFFF))

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        self.ids.append(doc_id)
        self._frame(ids.astype("<u4", copy=False).tobytes())

    def close(self) -> None:
        flags = np.array([i is None for i in self.ids], np.uint8)
        self._frame(np.array([i or 0 for i in self.ids], "<i8").tobytes() + flags.tobytes())
        table = b"".join(self.entries) + struct.pack("<IBI", len(self.entries), CHECKSUM_FLAG, SEEKABLE_MAGIC)
        self.out.write(struct.pack("<II", SKIPPABLE_MAGIC, len(table)) + table)


class ShardReader:
    """Random access to the documents of a shard; `source` is a seekable binary file."""

    def __init__(self, source, size: int):
        self.source = source
        source.seek(size - 9)
        n, flags, magic = struct.unpack("<IBI", source.read(9))
        if magic != SEEKABLE_MAGIC or flags != CHECKSUM_FLAG:
            raise ValueError("no seek table at the end of the file")
        source.seek(size - 9 - 12 * n)
        table = np.frombuffer(source.read(12 * n), "<u4").reshape(n, 3)
        self.packed, self.sizes, self.sums = table[:, 0].astype(np.int64), table[:, 1].astype(np.int64), table[:, 2]
        self.starts = np.cumsum(self.packed) - self.packed
        self.decompress = zstandard.ZstdDecompressor().decompress
        listed = self._frame(n - 1)
        n_docs = n - 1
        ids, null = np.frombuffer(listed[: 8 * n_docs], "<i8"), np.frombuffer(listed[8 * n_docs :], np.uint8)
        self.doc_ids = [None if z else i for i, z in zip(ids.tolist(), null.tolist(), strict=True)]

    def _frame(self, k: int) -> bytes:
        self.source.seek(int(self.starts[k]))
        data = self.decompress(self.source.read(int(self.packed[k])), max_output_size=int(self.sizes[k]))
        if xxhash.xxh64_intdigest(data) & 0xFFFFFFFF != self.sums[k]:
            raise ValueError(f"checksum of frame {k} differs")
        return data

    def ids(self, k: int) -> np.ndarray:
        """Ids of the k-th document of the shard; reads its frame only."""
        return np.frombuffer(self._frame(k), "<u4")

    def __len__(self) -> int:
        return len(self.doc_ids)


def _filesystem(folder: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(folder) if "://" in folder or folder.startswith("file:") else (pafs.LocalFileSystem(), folder)


def write_token_files(
    docs: DataFrame, vocab_path: str, end_id: int, folder: str | None = None, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """Encode and write all documents; the manifest has a row per shard.

    shard (in id order), path, n_docs, n_tokens, bytes, min_id, max_id.
    """
    folder = folder or new_path(docs.sparkSession, "token-files")

    @tidied
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = id_encoder(vocab_path, True)
        shard, fs, writer = TaskContext.get().partitionId(), None, None
        n_tokens = 0
        for batch in batches:
            doc_ids = batch.column(0).to_pylist()
            if doc_ids and writer is None:
                fs, root = _filesystem(folder)
                fs.create_dir(root, recursive=True)
                mine = f"{root}/.attempt-{uuid.uuid4().hex}"
                out = fs.open_output_stream(mine)
                writer = ShardWriter(out)
            for lo, _, counts, flat in encoder.slices(batch.column(1)):
                sizes = counts + 1
                ends = np.cumsum(sizes)
                ids = np.full(int(sizes.sum()), end_id, "<u4")
                ids[np.repeat(ends - sizes, counts) + ragged(counts)] = flat
                n_tokens += len(ids)
                for j, (a, b) in enumerate(zip((ends - sizes).tolist(), ends.tolist(), strict=True)):
                    writer.add(doc_ids[lo + j], ids[a:b])
        if writer is None:
            return
        writer.close()
        size = out.tell()
        out.close()
        path = f"{root}/shard-{shard:06d}.zst"
        known = [i for i in writer.ids if i is not None]
        fs.move(mine, path)
        yield pa.RecordBatch.from_pydict({"shard": [shard], "path": [path], "n_docs": [len(writer.ids)], "n_tokens": [n_tokens], "bytes": [size], "min_id": pa.array([known[0] if known else None], pa.int64()), "max_id": pa.array([known[-1] if known else None], pa.int64())})

    order = [F.col(c).asc_nulls_first() for c in ("id", "tag")]
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"), text_tag(F.col(text_col)).alias("tag"))
    ranged = rows.repartitionByRange(*order).sortWithinPartitions(*order).select("id", "text")
    manifest = ranged.mapInArrow(write, "shard long, path string, n_docs long, n_tokens long, bytes long, min_id long, max_id long")
    out = materialize(manifest, "token-manifest")
    out._subvote_folder = folder
    for name in list_names(docs.sparkSession, folder):  # of attempts that were lost
        if name.startswith(".attempt-"):
            delete(docs.sparkSession, f"{folder}/{name}")
    return out


def read_token_files(manifest: DataFrame, folder: str) -> DataFrame:
    """One row per document, read from the shards: id, start, n_tokens, ids_crc32.

    `start` counts the ids of all documents before it, over all shards.
    """
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    shards = manifest.withColumn("_start", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)).cast("long"))
    shards = shards.select("shard", "path", "_start", "bytes").repartition(max(1, manifest.count()), "shard")

    @tidied
    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, _ = _filesystem(folder)
        for batch in batches:
            for row in batch.to_pylist():
                with fs.open_input_file(row["path"]) as source:
                    reader, at = ShardReader(source, row["bytes"]), row["_start"]
                    for lo in range(0, len(reader), 4096):
                        hi = min(lo + 4096, len(reader))
                        frames = [reader._frame(k) for k in range(lo, hi)]
                        sizes = np.fromiter((len(x) // 4 for x in frames), np.int64, hi - lo)
                        starts = at + np.cumsum(sizes) - sizes
                        at += int(sizes.sum())
                        yield pa.RecordBatch.from_arrays(
                            [pa.array(reader.doc_ids[lo:hi], pa.int64()), pa.array(starts), pa.array(sizes), pa.array([zlib.crc32(x) for x in frames], pa.int64())],
                            ["doc_id", "start", "n_tokens", "ids_crc32"],
                        )

    return shards.mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long")


def fetch_documents(manifest: DataFrame, folder: str, wanted: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(doc_id, ids) of the documents asked for; of the shards' frames, only theirs are read.

    Shards whose range of ids holds none of the wanted ones are not opened.  The others give
    their directories (8 bytes a document), which are joined with the wanted ids, and every
    (shard, run of frames) that is left is read by itself.  Ids that are not there give no
    row, repeated ids give all their documents, a null id asks for nothing.
    """
    wanted = wanted.select(F.col(id_col).cast("long").alias("doc_id")).filter("doc_id is not null").distinct()
    ends = wanted.agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"))
    shards = manifest.crossJoin(F.broadcast(ends)).filter("max_id >= lo and min_id <= hi").select("path", "bytes")  # one row of ends

    @tidied
    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, _ = _filesystem(folder)
        for batch in batches:
            for row in batch.to_pylist():
                with fs.open_input_file(row["path"]) as source:
                    ids = ShardReader(source, row["bytes"]).doc_ids
                for lo in range(0, len(ids), 65536):
                    part = ids[lo : lo + 65536]
                    same = [pa.array([row[c]] * len(part)) for c in ("path", "bytes")]
                    yield pa.RecordBatch.from_arrays([*same, pa.array(range(lo, lo + len(part)), pa.int64()), pa.array(part, pa.int64())], ["path", "bytes", "frame", "doc_id"])

    @tidied
    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, _ = _filesystem(folder)
        for batch in batches:
            for row in batch.to_pylist():
                with fs.open_input_file(row["path"]) as source:
                    reader = ShardReader(source, row["bytes"])
                    for k in sorted(row["frames"]):
                        ids = reader.ids(k).astype(np.int64)
                        yield pa.RecordBatch.from_arrays([pa.array([reader.doc_ids[k]], pa.int64()), pa.array([ids], pa.list_(pa.int64()))], ["doc_id", "ids"])

    places = shards.repartition("path").mapInArrow(listed, "path string, bytes long, frame long, doc_id long")
    places = places.join(wanted, "doc_id").withColumn("run", F.floor(F.col("frame") / 4096))
    return places.groupBy("path", "bytes", "run").agg(F.collect_list("frame").alias("frames")).mapInArrow(fetch, "doc_id long, ids array<long>")
