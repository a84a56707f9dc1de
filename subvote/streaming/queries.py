"""Streaming queries: each runs a stream over the files of a table to its end and returns what it wrote."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subvote.operators.engine import IndexParams, SearchParams, build_index, search
from subvote.session import scratch
from subvote.sources import vectors as sources
from subvote.sources.tables import load
from subvote.streaming import engine


def _folder(spark: SparkSession) -> str:
    return scratch(spark, "stream")


def _events(spark: SparkSession, sf_dir: str, folder: str, parts: int = 4) -> DataFrame:
    """The events as a stream of files in time order, with one late marker far behind at the end."""
    events = load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    events.repartitionByRange(parts, "ts").sortWithinPartitions("ts").write.parquet(f"{folder}/in")
    return engine.file_stream(spark, f"{folder}/in", events.schema.simpleString()[7:-1].replace(":", " "), 1)


def _sink(df: DataFrame, folder: str, mode: str = "append") -> DataFrame:
    engine.run_once(df.writeStream.format("parquet").outputMode(mode).option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/cp"))
    return df.sparkSession.read.schema(df.schema).parquet(f"{folder}/out")


def q_stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly counts of the hours that the watermark has closed."""
    folder = _folder(spark)
    out = _sink(engine.windowed_counts(_events(spark, sf_dir, folder, 1)), folder)
    return out.select("event_type", "n", F.round("total", 4).alias("total"), F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"))


def q_stream_sliding(spark, sf_dir):
    folder = _folder(spark)
    out = _sink(engine.windowed_counts(_events(spark, sf_dir, folder, 1), "2 hours", "1 hour"), folder)
    return out.select("event_type", "n", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"))


def q_stream_sessions(spark, sf_dir):
    folder = _folder(spark)
    out = _sink(engine.session_counts(_events(spark, sf_dir, folder, 1)), folder)
    return out.select("user_id", "n", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"))


def q_stream_dedup(spark, sf_dir):
    """Every event sent twice; each id comes out once."""
    folder = _folder(spark)
    events = _events(spark, sf_dir, folder)
    twice = events.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    return _sink(engine.deduplicated(twice, late="3650 days"), folder).select("event_id", "user_id")


def q_stream_join(spark, sf_dir):
    folder = _folder(spark)
    events = _events(spark, sf_dir, folder)
    out = engine.purchases_after_views(events.filter("event_type = 'view'"), events.filter("event_type = 'purchase'"), late="3650 days")
    return _sink(out, folder)


def q_stream_user_totals(spark, sf_dir):
    """Stateful totals per user; the last row of each user is its batch total."""
    folder = _folder(spark)
    totals = engine.user_totals(_events(spark, sf_dir, folder).select("user_id", "value"))
    state: dict[str, str] = {}

    def write(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{folder}/out/b={number}")
        state["any"] = "yes"

    engine.run_once(totals.writeStream.outputMode("update").foreachBatch(write).option("checkpointLocation", f"{folder}/cp"))
    rows = spark.read.parquet(f"{folder}/out")
    return rows.groupBy("user_id").agg(F.max("n").alias("n"), F.round(F.max_by("total", "n"), 4).alias("total"))


def _vector_files(spark: SparkSession, df: DataFrame, folder: str, parts: int) -> DataFrame:
    df.select("id", "vec").repartitionByRange(parts, "id").write.parquet(f"{folder}/vectors")
    return engine.file_stream(spark, f"{folder}/vectors", "id long, vec array<double>", 1)


def q_stream_append(spark, sf_dir):
    """Half of the base arrives as a stream; with all cells open, the result is exact."""
    folder = _folder(spark)
    base, queries = sources.split(sources.embeddings(spark, sf_dir))
    index = build_index(base.filter("id % 2 = 0"), IndexParams(m=8, k=8, iters=2, policy="never", shard_rows=256, storage="f8"))
    index = engine.append_stream(_vector_files(spark, base.filter("id % 2 = 1"), folder, 3), index, f"{folder}/cp")
    return search(index, queries, 10, SearchParams("guaranteed", 1.0, 0.01))


def q_stream_top_alerts(spark, sf_dir):
    """The event that holds each user's largest value after the whole stream, from the alerts."""
    folder = _folder(spark)
    alerts = _sink(engine.top_alerts(_events(spark, sf_dir, folder, 1), k=3, idle=10 * 365 * 86400, late="3650 days"), folder)
    best = alerts.filter("kind = 'alert'").groupBy("user_id").agg(F.max("value").alias("top"))
    return best.select("user_id", F.round("top", 4).alias("top"))


def q_stream_queries(spark, sf_dir):
    """Queries arrive as a stream against a fixed index."""
    folder = _folder(spark)
    base, queries = sources.split(sources.embeddings(spark, sf_dir))
    index = build_index(base, IndexParams(m=8, k=8, init="id_stride", iters=0, policy="never", shard_rows=256, storage="f8"))
    engine.query_stream(_vector_files(spark, queries, folder, 3), index, 10, SearchParams("guaranteed", 0.2, 0.25), f"{folder}/out", f"{folder}/cp")
    return spark.read.parquet(f"{folder}/out").select("query_id", "rank", "id", "dist2")


def q_stream_drift(spark, sf_dir):
    """Isotropic vectors first, concentrated ones later: the monitor asks for a rebuild."""
    folder = _folder(spark)
    calm = sources.embeddings(spark, sf_dir)
    loud = sources.decayed(calm, 0.8).select((F.col("id") + 1_000_000).alias("id"), F.transform("vec", lambda x: x * 30).alias("vec"))
    monitor = engine.DriftMonitor(64, folder=f"{folder}/state")
    rows = monitor.watch(_vector_files(spark, calm.unionByName(loud), folder, 4), f"{folder}/cp")
    return spark.createDataFrame([(*r, monitor.rebuild) for r in rows], "batch int, rows long, cev double, rotate boolean, rebuild boolean")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, f in globals().items() if name.startswith("q_stream_")}


def oracle_sql() -> dict[str, str]:
    from subvote.plans import ann_oracles

    ann = ann_oracles.oracle_sql()
    return {
        "q_stream_dedup": "SELECT event_id, user_id FROM events",
        "q_stream_user_totals": "SELECT user_id, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY user_id",
        "q_stream_join": "SELECT p.event_id AS purchase_id, v.event_id AS view_id FROM events p JOIN events v ON p.user_id = v.user_id AND p.event_type = 'purchase' AND v.event_type = 'view' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR",
        "q_stream_top_alerts": "SELECT user_id, round(max(value), 4) AS top FROM events WHERE value IS NOT NULL GROUP BY user_id",
        "q_stream_append": ann["q_exact_knn"],
        "q_stream_queries": ann["q_search_guaranteed"],
        "q_stream_tumbling": "WITH w AS (SELECT date_trunc('hour', ts) AS s, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL) SELECT event_type, n, total, strftime(s, '%Y-%m-%d %H:%M:%S') AS start FROM w WHERE s + INTERVAL 1 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR",
        "q_stream_sliding": "WITH w AS (SELECT date_trunc('hour', ts) - INTERVAL 1 HOUR * o AS s, event_type, count(*) AS n FROM events, (VALUES (0), (1)) v(o) GROUP BY ALL) SELECT event_type, n, strftime(s, '%Y-%m-%d %H:%M:%S') AS start FROM w WHERE s + INTERVAL 2 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR",
        "q_stream_sessions": """WITH m AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w >= INTERVAL 30 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS cut, event_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
n AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM m)
SELECT user_id, count(*) AS n, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start FROM n GROUP BY user_id, s HAVING max(ts) + INTERVAL 30 MINUTE <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR""",
    }
