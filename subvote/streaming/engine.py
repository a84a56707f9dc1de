"""Streaming around the index: appended vectors, streamed queries, drift, and event windows."""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from subvote.operators import spectral
from subvote.operators.engine import AnnIndex, SearchParams, append_saved, exists, load_index, save_index, search


def run_once(writer) -> None:
    """Process what is there and stop."""
    query: StreamingQuery = writer.trigger(availableNow=True).start()
    query.awaitTermination()


def file_stream(spark: SparkSession, path: str, schema: str, per_batch: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(schema)
    return (reader.option("maxFilesPerTrigger", per_batch) if per_batch else reader).parquet(path)


def append_stream(vectors: DataFrame, index: AnnIndex, checkpoint: str, after: Callable[[AnnIndex, int], None] | None = None, path: str | None = None) -> AnnIndex:
    """Encode every micro-batch with the frozen codebooks and add it as delta shards.

    The index lives at `path` (beside the checkpoint by default), which a first run saves;
    a batch writes a folder by its number there.  So a restart goes on with all that was
    added before, and a batch that runs again replaces itself.
    """
    spark, path = index.spark, path or f"{checkpoint}-index"
    if not exists(spark, f"{path}/meta/_SUCCESS"):
        save_index(index, path)

    def add(batch: DataFrame, number: int) -> None:
        append_saved(index, batch.select("id", "vec"), path, number)
        if after is not None:
            after(load_index(spark, path), number)

    run_once(vectors.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint))
    return load_index(spark, path)


def query_stream(queries: DataFrame, index: AnnIndex, k: int, params: SearchParams, out: str, checkpoint: str) -> None:
    """Answer every micro-batch of queries against a fixed index; a batch writes a folder of its
    own, so a batch that runs again replaces itself."""

    def answer(batch: DataFrame, number: int) -> None:
        search(index, batch.select("id", "vec"), k, params).write.mode("overwrite").parquet(f"{out}/batch={number}")

    run_once(queries.writeStream.foreachBatch(answer).option("checkpointLocation", checkpoint))


def windowed_counts(events: DataFrame, size: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Tumbling or sliding counts and sums with a watermark."""
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    out = events.withWatermark("ts", late).groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n", "total")


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    out = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count("*").alias("n"))
    return out.select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n")


def deduplicated(events: DataFrame, key: str = "event_id", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def purchases_after_views(views: DataFrame, purchases: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: purchases of a user at most `within` after a view."""
    v = views.withWatermark("ts", late).select(F.col("user_id").alias("v_user"), F.col("ts").alias("v_ts"), F.col("event_id").alias("view_id"))
    p = purchases.withWatermark("ts", late).select("user_id", "ts", F.col("event_id").alias("purchase_id"))
    return p.join(v, F.expr(f"user_id = v_user AND ts >= v_ts AND ts <= v_ts + INTERVAL {within}")).select("purchase_id", "view_id")


def running_totals(key: tuple[Any, ...], batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    """Per user: number of events and sum of values so far, one row per micro-batch."""
    n, total = state.get if state.exists else (0, 0.0)
    for batch in batches:
        n, total = n + len(batch), total + float(batch["value"].sum())
    state.update((n, total))
    yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})


def user_totals(events: DataFrame) -> DataFrame:
    from pyspark.sql.streaming.state import GroupStateTimeout

    return events.groupBy("user_id").applyInPandasWithState(running_totals, "user_id long, n long, total double", "n long, total double", "update", GroupStateTimeout.NoTimeout)


def top_values(key: tuple[Any, ...], batches: Iterator[pd.DataFrame], state, k: int, idle_ms: int) -> Iterator[pd.DataFrame]:
    """Per user: an alert for every event that enters the k largest values seen so far.

    State is k values.  It goes with a last row of kind `gone` once the watermark has passed
    `idle_ms` after the user's last event.
    """
    if state.hasTimedOut:
        best, last = state.get
        state.remove()
        yield pd.DataFrame({"user_id": [key[0]], "kind": ["gone"], "event_id": pd.array([None], "Int64"), "value": [min(best)], "place": pd.array([len(best)], "Int32")})
        return
    best, last = (list(state.get[0]), state.get[1]) if state.exists else ([], 0)
    rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
    found = []
    for event_id, value, ts in zip(rows["event_id"], rows["value"], rows["ts"], strict=True):
        last = max(last, int(ts.timestamp() * 1000))
        if len(best) < k or value > best[-1]:
            best = sorted([*best, float(value)], reverse=True)[:k]
            found.append((key[0], "alert", int(event_id), float(value), best.index(float(value)) + 1))
    state.update((best, last))
    state.setTimeoutTimestamp(max(last + idle_ms, state.getCurrentWatermarkMs() + 1))
    yield pd.DataFrame(found, columns=["user_id", "kind", "event_id", "value", "place"])


def top_alerts(events: DataFrame, k: int = 3, idle: int = 3600, late: str = "1 hour") -> DataFrame:
    """Alerts of the k largest values per user; state expires after `idle` seconds without events."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    def run(key: tuple[Any, ...], batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        yield from top_values(key, batches, state, k, 1000 * idle)

    rows = events.withWatermark("ts", late).select("user_id", "event_id", "value", "ts").groupBy("user_id")
    schema = "user_id long, kind string, event_id long, value double, place int"
    return rows.applyInPandasWithState(run, schema, "best array<double>, last long", "append", GroupStateTimeout.EventTimeTimeout)


class DriftMonitor:
    """Mergeable sufficient statistics of a stream of vectors: when would the rotate decision flip?

    With a folder, the statistics after every batch are stored there by the batch's number: a
    restart goes on from them, and a batch that runs again starts from its predecessor's.
    """

    def __init__(self, dim: int, threshold: float = spectral.THRESHOLD, folder: str | None = None):
        self.dim, self.threshold, self.folder = dim, threshold, folder
        self._clear()

    def _clear(self) -> None:
        self.number, self.n, self.sum, self.gram = -1, 0, np.zeros(self.dim), np.zeros((self.dim, self.dim))
        self.history: list[tuple[int, int, float, bool]] = []

    def _load(self, spark: SparkSession, number: int) -> None:
        self._clear()
        path = f"{self.folder}/batch={number}"
        if number >= 0 and exists(spark, f"{path}/_SUCCESS"):
            row = spark.read.parquet(path).first()
            self.number, self.n, self.sum = number, row["n"], np.frombuffer(bytes(row["sum"]))
            self.gram = np.frombuffer(bytes(row["gram"])).reshape(self.dim, self.dim)
            self.history = [(int(a), int(b), float(c), bool(d)) for a, b, c, d in json.loads(row["history"])]

    def update(self, batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        if self.folder and self.number != number - 1:
            self._load(spark, number - 1)
        n, total, gram = spectral.moments(batch, self.dim)
        self.number, self.n, self.sum, self.gram = number, self.n + n, self.sum + total, self.gram + gram
        self.history.append((number, self.n, self.cev(), bool(self.cev() > self.threshold)))
        if self.folder:
            row = (self.n, bytearray(self.sum.tobytes()), bytearray(self.gram.tobytes()), json.dumps(self.history))
            spark.createDataFrame([row], "n long, sum binary, gram binary, history string").coalesce(1).write.mode("overwrite").parquet(f"{self.folder}/batch={number}")

    def cev(self) -> float:
        if self.n < 2:
            return 0.0
        return spectral.cev(spectral.eigenvalues((self.gram - np.outer(self.sum, self.sum) / self.n) / (self.n - 1)))

    def watch(self, vectors: DataFrame, checkpoint: str) -> list[tuple[int, int, float, bool]]:
        """(batch, rows so far, cev, rotate) after every micro-batch."""
        run_once(vectors.writeStream.foreachBatch(self.update).option("checkpointLocation", checkpoint))
        if self.folder and self.number < 0:  # nothing new: what was known before
            spark, last = vectors.sparkSession, -1
            while exists(spark, f"{self.folder}/batch={last + 1}/_SUCCESS"):
                last += 1
            self._load(spark, last)
        return self.history

    @property
    def rebuild(self) -> bool:
        """The decision at the end differs from the first one."""
        return bool(self.history) and self.history[0][3] != self.history[-1][3]
