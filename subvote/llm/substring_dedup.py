"""Substring deduplication with a log-structured fingerprint index.

A window is a run of `size` words.  Its fingerprint is the smallest hash among its runs of
`gram` words, at the leftmost place; neighbouring windows mostly share that place, so a
document is a list of fingerprint runs (fingerprint, first window, number of windows),
about one per eight words, and equal windows always have equal fingerprints.

The index is a folder of immutable runs, bucketed and sorted so that a merge join reads
them as they lie, and a manifest that names the runs in force.  It holds two kinds:

* marks: every fingerprint with how often it was seen and where first;
* windows: 128-bit digests of the whole windows behind fingerprints seen twice.

Batches come in order; a batch is

1. reduced to its fingerprints, which are merge-joined with all mark runs and itself;
2. verified: windows behind fingerprints seen twice, in the batch or where history had seen
   them once, are hashed whole (128 bits, other hashes than the fingerprints') and
   merge-joined with the window runs, which decides for good what of the batch is removed;
3. appended as one run of each kind; more than `fan_out` runs are compacted into one.

A window is removed if its words start earlier: in an earlier batch, or in this one by
(document id, null first; text digest; place).  Defined cases: null text has no words;
texts shorter than a window are left alone; a window that overlaps its own repeat is
removed from its second start on; rows that repeat an id with another text are documents
of their own, ordered by the digest of their text; rows equal in id and text are judged
alike and never against each other; an empty table gives no rows; other columns are
ignored.  A batch that is added again under its name gives what it gave before.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subvote.llm._store import discard, list_names, materialize, merge_joined, new_path, open_run, text_tag, write_run, write_text
from subvote.llm._text import U64, Words, as_long, ragged, roll, text_slices
from subvote.llm._worker import tidied

KEY = ("doc_id", "tag")
MARK_RUN, WINDOW_RUN = "mark:bigint,times:bigint,where:struct<doc_id:bigint,tag:bigint,first:int,n:int>", "a:bigint,b:bigint"
SPANS = "doc_id long, tag long, starts array<int>, ends array<int>"


def marks(words: Words, size: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(document, fingerprint, first window, windows) of all fingerprint runs of a slice."""
    n = len(words.starts)
    none = np.empty(0, np.int64)
    if n < size:
        return none, none.astype(U64), none, none
    value = roll(words.hashes, gram, 3)
    place = np.arange(len(value))
    span, have = size - gram + 1, 1
    least, where = value, place
    # Leftmost minimum over `span` neighbours, by doubling.
    while have < span:
        step = min(have, span - have)
        right = least[step:] < least[:-step]
        where = np.where(right, where[step:], where[:-step])
        least = np.where(right, least[step:], least[:-step])
        have += step
    doc = words.doc
    at = np.flatnonzero(doc[: n - size + 1] == doc[size - 1 :])
    if not len(at):
        return none, none.astype(U64), none, none
    place, doc = where[at], doc[at]
    head = np.ones(len(at), dtype=bool)
    head[1:] = (place[1:] != place[:-1]) | (doc[1:] != doc[:-1])
    edge = np.flatnonzero(head)
    first = at[edge] - words.first[doc[edge]]
    return doc[edge], value[place[edge]], first, np.diff(edge, append=len(at))


def keyed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, tag, text): rows of one id are told apart by the digest of their text."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), text_tag(F.col(text_col)).alias("tag"), F.col(text_col).alias("text"))


class FingerprintIndex:
    """Runs and manifest in `folder`; an index that is there is opened as it stands."""

    def __init__(self, spark: SparkSession, folder: str | None = None, size: int = 20, gram: int = 6, fan_out: int = 2, buckets: int | None = None):
        self.spark, self.folder = spark, folder or new_path(spark, "fingerprints")
        self.marks: list[DataFrame] = []
        self.windows: list[DataFrame] = []
        self.compactions, self.results = 0, {}
        manifests = [n for n in list_names(spark, self.folder) if n.startswith("manifest-") and n.endswith(".json")]
        self.version = 0
        if not manifests:
            self.size, self.gram, self.fan_out = size, gram, fan_out
            self.buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
            return
        found = json.loads("\n".join(r[0] for r in spark.read.text(f"{self.folder}/{manifests[-1]}").collect()))
        self.version, self.results, self.compactions = found["version"], found["results"], found["compactions"]
        self.size, self.gram, self.fan_out, self.buckets = found["size"], found["gram"], found["fan_out"], found["buckets"]
        self.marks = [self._open(n, MARK_RUN, ["mark"]) for n in found["marks"]]
        self.windows = [self._open(n, WINDOW_RUN, ["a", "b"]) for n in found["windows"]]

    def _open(self, name: str, schema: str, keys: list[str]) -> DataFrame:
        out = open_run(self.spark, f"{self.folder}/{name}", schema, keys, self.buckets)
        out._subvote_name = name
        return out

    def _write(self, df: DataFrame, kind: str, keys: list[str]) -> DataFrame:
        path = new_path(self.spark, kind).rsplit("/", 1)[1]
        out = write_run(df, f"{self.folder}/{path}", keys, self.buckets)
        out._subvote_name = path
        return out

    def _commit(self) -> None:
        """Name the runs in force; a job that dies before this leaves the former manifest."""
        self.version += 1
        names = lambda runs: [r._subvote_name for r in runs]
        state = {
            "version": self.version, "size": self.size, "gram": self.gram, "fan_out": self.fan_out, "buckets": self.buckets,
            "marks": names(self.marks), "windows": names(self.windows), "compactions": self.compactions, "results": self.results,
        }
        write_text(self.spark, f"{self.folder}/manifest-{self.version:08d}.json", json.dumps(state))

    def occurrences(self, docs: DataFrame) -> DataFrame:
        """(mark, doc_id, tag, first, n) of keyed rows."""
        size, gram = self.size, self.gram

        @tidied
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for lo, hi, buf, offs in text_slices(batch.column(2)):
                    doc, mark, first, n = marks(Words(buf, offs), size, gram)
                    at = pa.array(doc)
                    ids = [batch.column(c).slice(lo, hi - lo).take(at) for c in (0, 1)]
                    yield pa.RecordBatch.from_arrays([pa.array(as_long(mark)), *ids, pa.array(first.astype(np.int32)), pa.array(n.astype(np.int32))], ["mark", *KEY, "first", "n"])

        return docs.select(*KEY, "text").mapInArrow(run, "mark long, doc_id long, tag long, first int, n int")

    def add(self, docs: DataFrame, earlier: DataFrame | None = None, batch: str | None = None, keep: bool = True) -> DataFrame:
        """SPANS: the words of keyed rows that repeat, in this batch or after earlier ones.

        `earlier` holds the keyed rows of all earlier batches, whose texts are read where a
        fingerprint that was alone so far is met again.  With `keep`, the batch becomes part
        of the index, and its result is recorded under the name `batch`.
        """
        if batch is not None and batch in self.results:
            return self.spark.read.schema(SPANS).parquet(f"{self.folder}/{self.results[batch]}")
        seen = materialize(self.occurrences(docs), "marks")
        place = F.struct(*KEY, "first", "n")
        own = self._write(seen.groupBy("mark").agg(F.count("*").alias("times"), F.min(place).alias("where")), "mark-run", ["mark"])
        twice = self._lookup(own).filter("times > 1 or past_times > 0").select("mark", "past_times", "past_where")
        twice = merge_joined(twice, "mark-hits")
        hits = materialize(seen.join(twice.select("mark"), "mark").select(*KEY, "first", "n").distinct(), "hits")
        digests = self._digests(docs, hits, False)
        if earlier is not None:
            # An earlier place that was alone until now counts from now on.
            digests = digests.union(self._digests(earlier, twice.filter("past_times = 1").select("past_where.*").distinct(), True))
        found = digests.groupBy("a", "b").agg(F.max("old").alias("old"), F.min(F.struct(*KEY, "first")).alias("at"))
        found = self._write(found, "window-run", ["a", "b"])
        new = reduce(lambda rows, run: rows.join(run.select("a", "b"), ["a", "b"], "left_anti"), self.windows, found.filter("not old"))
        firsts = merge_joined(new.select("at.*"), "first-places")
        out = self._removed(hits, firsts)
        name = f"removed-{new_path(self.spark, 'r').rsplit('-', 1)[1]}"
        out.write.parquet(f"{self.folder}/{name}")
        out = self.spark.read.schema(SPANS).parquet(f"{self.folder}/{name}")
        for table in (seen, twice, hits, firsts):
            discard(table)
        if keep:
            if batch is not None:
                self.results[batch] = name
            self.marks.append(own)
            self.windows.append(found)
            self._compact() if len(self.marks) > self.fan_out else self._commit()
        else:
            discard(own)
            discard(found)
        return out

    def _lookup(self, own: DataFrame) -> DataFrame:
        """Adds past_times and past_where: one merge join per run, bucket by bucket."""
        place = own.schema["where"].dataType
        out = own.withColumn("past_times", F.lit(0).cast("long")).withColumn("past_where", F.lit(None).cast(place))
        for run in self.marks:
            run = run.select("mark", F.col("times").alias("run_times"), F.col("where").alias("run_where"))
            out = out.join(run.hint("merge"), "mark", "left").select(
                "mark", "times", "where", (F.col("past_times") + F.coalesce("run_times", F.lit(0))).alias("past_times"), F.least("past_where", "run_where").alias("past_where")
            )
        return out

    def _digests(self, docs: DataFrame, hits: DataFrame, old: bool) -> DataFrame:
        """(a, b, old, doc_id, tag, first): whole windows of hits, hashed over all their words."""
        size = self.size
        texts = docs.join(_per_row(hits, "hits", "first", "n"), _same_row()).select(*KEY, "text", "hits")

        @tidied
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for lo, hi, buf, offs in text_slices(batch.column(2)):
                    words = Words(buf, offs)
                    if len(words.starts) < size:
                        continue
                    chosen, owners = [], []
                    for d in range(hi - lo):
                        w = _windows(*_hit_arrays(batch.column(3), lo + d))
                        w = w[w <= words.counts[d] - size]
                        chosen.append(w)
                        owners.append(np.full(len(w), d))
                    window, owner = np.concatenate(chosen), np.concatenate(owners)
                    at, rows = window + words.first[owner], pa.array(owner)
                    one, two = roll(words.hashed(60), size, 5)[at], roll(words.hashed(80), size, 9)[at]
                    ids = [batch.column(c).slice(lo, hi - lo).take(rows) for c in (0, 1)]
                    yield pa.RecordBatch.from_arrays([pa.array(as_long(one)), pa.array(as_long(two)), pa.array(np.full(len(at), old)), *ids, pa.array(window.astype(np.int32))], ["a", "b", "old", *KEY, "first"])

        return texts.mapInArrow(run, "a long, b long, old boolean, doc_id long, tag long, first int")

    def _removed(self, hits: DataFrame, firsts: DataFrame) -> DataFrame:
        """SPANS per row: its hit windows without those that are the first of their text."""
        size = self.size
        rows = _per_row(hits, "hits", "first", "n")
        firsts = firsts.groupBy(*KEY).agg(F.collect_list("first").alias("firsts"))
        rows = rows.join(firsts, _same_row(), "left").select(F.col("k_doc_id").alias("doc_id"), F.col("k_tag").alias("tag"), "hits", "firsts")

        @tidied
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                starts, ends, some = [], [], []
                for row in range(len(batch)):
                    w = _windows(*_hit_arrays(batch.column(2), row))
                    if batch.column(3)[row].is_valid:
                        w = np.setdiff1d(w, batch.column(3)[row].values.to_numpy())
                    some.append(len(w) > 0)
                    cut = np.flatnonzero(np.diff(w) > size)
                    starts.append(w[np.concatenate([[0], cut + 1])].astype(np.int32) if len(w) else w.astype(np.int32))
                    ends.append((w[np.concatenate([cut, [len(w) - 1]])] + size).astype(np.int32) if len(w) else w.astype(np.int32))
                kind = pa.list_(pa.int32())
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(starts, kind), pa.array(ends, kind)], [*KEY, "starts", "ends"]).filter(pa.array(some, pa.bool_()))

        return rows.mapInArrow(run, SPANS)

    def _compact(self) -> None:
        """Merge all runs of a kind into one, commit, then delete the merged ones."""
        old = [*self.marks, *self.windows]
        # Files are read as plain ones: a union of bucketed scans passes for partitioned, which it is not.
        plain = lambda runs: self.spark.read.schema(runs[0].schema).parquet(*[r._subvote_path for r in runs])
        marks_ = plain(self.marks).groupBy("mark").agg(F.sum("times").alias("times"), F.min("where").alias("where"))
        windows = plain(self.windows).select("a", "b").distinct()
        self.marks = [self._write(marks_, "mark-run", ["mark"])]
        self.windows = [self._write(windows, "window-run", ["a", "b"])]
        self.compactions += 1
        self._commit()
        for run in old:
            discard(run)

    def drop(self) -> None:
        """Delete all runs, for an index that is not wanted any longer; results stay."""
        for run in (*self.marks, *self.windows):
            discard(run)
        self.marks, self.windows = [], []


def _per_row(rows: DataFrame, name: str, *columns: str) -> DataFrame:
    """(k_doc_id, k_tag, name): the places of every row as one list, bounded by its length."""
    return rows.groupBy(F.col("doc_id").alias("k_doc_id"), F.col("tag").alias("k_tag")).agg(F.collect_list(F.struct(*columns)).alias(name))


def _same_row():
    return F.col("doc_id").eqNullSafe(F.col("k_doc_id")) & (F.col("tag") == F.col("k_tag"))


def _windows(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Sorted distinct windows of a document's hits."""
    return np.unique(np.repeat(first, n) + ragged(n.astype(np.int64)))


def _hit_arrays(column: pa.Array, row: int) -> tuple[np.ndarray, np.ndarray]:
    flat = column[row].values
    return flat.field("first").to_numpy(), flat.field("n").to_numpy()


def remove_repeats(docs: DataFrame, size: int = 20, batches: int = 4, gram: int = 6, fan_out: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, n_removed, kept_text, kept_sha256 of every row.

    The table is ingested in `batches` ranges of ascending ids, as a growing corpus would be.
    """
    docs = keyed(docs, id_col, text_col)
    index = FingerprintIndex(docs.sparkSession, None, size, gram, fan_out)
    shares = [i / batches for i in range(1, batches)]
    cuts = docs.select(F.percentile_approx("doc_id", shares or [0.5], 1000)).first()[0] if batches > 1 else []
    cuts = sorted(set(cuts or []))
    spans = None
    for i, low in enumerate([None, *cuts]):
        below = F.col("doc_id").isNull() | (F.col("doc_id") <= cuts[i]) if i < len(cuts) else F.lit(True)
        above, before = (F.col("doc_id") > low, F.col("doc_id").isNull() | (F.col("doc_id") <= low)) if i else (F.lit(True), None)
        found = index.add(docs.filter(below & above), docs.filter(before) if i else None, keep=i < len(cuts))
        spans = found if spans is None else spans.union(found)
    index.drop()
    return drop_spans(docs, spans)


def drop_spans(docs: DataFrame, spans: DataFrame) -> DataFrame:
    """Remove the words of SPANS from keyed rows."""
    plan = spans.select(F.col("doc_id").alias("k_doc_id"), F.col("tag").alias("k_tag"), "starts", "ends")
    rows = docs.join(plan, _same_row(), "left").select("doc_id", "text", "starts", "ends")

    @tidied
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, texts, starts, ends = batch.columns
            n_words, n_removed, kept, digest = [], [], [], []
            volume, lo = 0, 0
            for row in range(len(batch)):
                words = texts[row].as_buffer().to_pybytes().split() if texts[row].is_valid else []
                n_words.append(len(words))
                if starts[row].is_valid:
                    left, at = [], 0
                    for a, b in zip(starts[row].values.to_pylist(), ends[row].values.to_pylist(), strict=True):
                        left += words[at:a]
                        at = b
                    words = left + words[at:]
                n_removed.append(n_words[-1] - len(words))
                text = b" ".join(words)
                kept.append(text)
                digest.append(hashlib.sha256(text).hexdigest())
                volume += len(text)
                if volume > 8 << 20 or row == len(batch) - 1:
                    yield pa.RecordBatch.from_arrays(
                        [ids.slice(lo, row + 1 - lo), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(kept, pa.binary()).cast(pa.string()), pa.array(digest)],
                        ["doc_id", "n_words", "n_removed", "kept_text", "kept_sha256"],
                    )
                    n_words, n_removed, kept, digest, volume, lo = [], [], [], [], 0, row + 1

    return rows.mapInArrow(run, "doc_id long, n_words long, n_removed long, kept_text string, kept_sha256 string")
