"""Vector views `(id long, vec array<double>)` of the tables, and vector files."""

from __future__ import annotations

import struct
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subvote.operators.arrow import lists, matrix
from subvote.sources.tables import load

_VEC = "id long, vec array<double>"


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"))


def decayed(df: DataFrame, rate: float) -> DataFrame:
    """Component j times rate**j: variance concentrates in the leading dimensions."""
    return df.withColumn("vec", F.transform("vec", lambda x, j: x * F.pow(F.lit(rate), j)))


def mixed(df: DataFrame, rank: int = 12, share: float = 0.1) -> DataFrame:
    """Component j becomes e[j mod rank] + share * e[j]: dimensions correlate across the vector."""
    return df.withColumn("vec", F.transform("vec", lambda x, j: F.element_at("vec", (j % rank + 1).cast("int")) + share * x))


def hashed_text(rows: DataFrame, id_col: str, text: F.Column, dim: int) -> DataFrame:
    """Signed feature hashing of lower-case tokens by md5, normalised.

    Sparse counts are summed per (row, slot) in the JVM and laid out by position in Arrow
    batches, so no vector is shuffled in dense form.  Texts that come in fewer partitions than
    there are cores (few files or row groups) are dealt out first.
    """
    cores = rows.sparkSession.sparkContext.defaultParallelism
    if rows.rdd.getNumPartitions() < cores:
        rows = rows.repartition(cores)
    token = F.explode(F.filter(F.split(F.lower(F.trim(text)), "\\s+"), lambda t: t != ""))
    digest = F.md5(F.col("token").cast("binary"))
    slot = F.pmod(F.conv(F.substring(digest, 1, 8), 16, 10).cast("long"), F.lit(dim)).cast("int")
    sign = F.when(F.substring(digest, 9, 1) >= "8", -1.0).otherwise(1.0)
    counts = rows.select(F.col(id_col).alias("id"), token.alias("token")).select("id", slot.alias("slot"), sign.alias("sign"))
    sums = counts.groupBy("id", "slot").agg(F.sum("sign").alias("x")).filter("x != 0")
    pairs = F.collect_list(F.struct("slot", "x"))
    sparse = sums.groupBy("id").agg(pairs.alias("m"), F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm"))

    def lay_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, len(whole), 256):
                batch = whole.slice(lo, 256)
                held, x = batch.column(1).flatten(), np.zeros((len(batch), dim))
                at = np.repeat(np.arange(len(batch)), batch.column(1).value_lengths().to_numpy())
                x[at, held.field(0).to_numpy()] = held.field(1).to_numpy()
                yield pa.RecordBatch.from_arrays([batch.column(0), lists(x / batch.column(2).to_numpy()[:, None])], ["id", "vec"])

    return sparse.select("id", "m", "norm").mapInArrow(lay_out, _VEC)


def documents(spark: SparkSession, sf_dir: str, dim: int = 768) -> DataFrame:
    return hashed_text(load(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id", F.col("text"), dim)


def pages(spark: SparkSession, sf_dir: str, dim: int = 768) -> DataFrame:
    return hashed_text(load(spark, sf_dir, "pages").select("page_id", "html"), "page_id", F.regexp_replace("html", "<[^>]*>", " "), dim)


def _values(column: DataFrame, most: int) -> list[str]:
    """Distinct values in order, one dimension (or more) each; a column with too many is refused."""
    name = column.columns[0]
    found = [r[0] for r in column.filter(F.col(name).isNotNull()).distinct().orderBy(name).limit(most + 1).collect()]
    if len(found) > most:
        raise ValueError(f"{name} has more than {most} values")
    return found


def event_profiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per user: counts by (hour, event type) in a fixed order, 24 x 5 dimensions."""
    kinds = ["click", "error", "login", "purchase", "view"]
    events = load(spark, sf_dir, "events").select("user_id", F.hour("ts").alias("hour"), "event_type")
    known = _values(events.select("event_type"), 64)
    kinds = known or kinds
    slot = F.col("hour") * len(kinds) + F.array_position(F.array(*[F.lit(k) for k in kinds]), F.col("event_type")) - 1
    wide = events.select("user_id", slot.cast("int").alias("slot")).groupBy("user_id").pivot("slot", list(range(24 * len(kinds)))).count()
    columns = [F.coalesce(F.col(f"`{i}`"), F.lit(0)).cast("double") for i in range(24 * len(kinds))]
    return wide.select(F.col("user_id").alias("id"), F.array(*columns).alias("vec"))


def customer_spend(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per customer: spend by brand, brands in order."""
    parts = load(spark, sf_dir, "part").select("p_partkey", "p_brand")
    brands = _values(parts.select("p_brand"), 1000)
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_extendedprice")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    spend = lines.join(orders, lines.l_orderkey == orders.o_orderkey).join(parts, lines.l_partkey == parts.p_partkey)
    wide = spend.groupBy("o_custkey").pivot("p_brand", brands).agg(F.sum("l_extendedprice"))
    return wide.select(F.col("o_custkey").alias("id"), F.array(*[F.coalesce(F.col(f"`{b}`"), F.lit(0.0)) for b in brands]).alias("vec"))


def synthetic(spark: SparkSession, n: int, dim: int, spectrum: float = 1.0, latent: int | None = None, seed: int = 7, partitions: int | None = None) -> DataFrame:
    """Seeded Gaussian vectors; component j is scaled by spectrum**j, `latent` < dim gives a low-rank cloud.

    Every row depends on its id and the seed alone, so retries and other partitionings agree.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scale = np.power(spectrum, np.arange(dim))
        base = np.random.default_rng(seed).standard_normal((latent, dim)) / np.sqrt(latent) if latent else None
        for batch in batches:
            ids = batch.column(0).to_numpy()
            for lo in range(0, len(ids), 1024):
                part = ids[lo : lo + 1024]
                x = np.stack([np.random.default_rng((seed, int(i))).standard_normal(latent or dim) for i in part])
                x = (x @ base if latent else x) * scale
                flat = pa.array(x.ravel())
                offsets = pa.array(np.arange(len(part) + 1, dtype=np.int32) * dim)
                yield pa.RecordBatch.from_arrays([pa.array(part), pa.ListArray.from_arrays(offsets, flat)], ["id", "vec"])

    return (spark.range(n) if partitions is None else spark.range(0, n, 1, partitions)).mapInArrow(run, _VEC)


def vectors(spark: SparkSession, sf_dir: str, code: str) -> DataFrame:
    """A vector view by its code: E64, E64-decay90, E64-mix, DOC-768, PAGE-768, EVT-120, CUST-P."""
    name, _, option = code.partition("-")
    if name == "E64":
        base = embeddings(spark, sf_dir)
        if option.startswith("decay"):
            return decayed(base, int(option[5:]) / 100)
        return mixed(base) if option == "mix" else base
    if name == "DOC":
        return documents(spark, sf_dir, int(option))
    if name == "PAGE":
        return pages(spark, sf_dir, int(option))
    if name == "EVT":
        return event_profiles(spark, sf_dir)
    if name == "CUST":
        return customer_spend(spark, sf_dir)
    raise ValueError(f"no vector view {code}")


def split(df: DataFrame, every: int = 10) -> tuple[DataFrame, DataFrame]:
    """(base, queries): ids divisible by `every` ask, the others answer."""
    return df.filter(F.col("id") % every != 0), df.filter(F.col("id") % every == 0)


def write_vector_files(df: DataFrame, folder: str, files: int) -> DataFrame:
    """Write vectors as length-prefixed float records, one file per range of ids.

    Every task streams its own file under a name of its attempt and renames it when whole.
    Returns (path, first, n) per file: `first` counts the rows of the files before it.
    """

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = pafs.FileSystem.from_uri(folder) if ":/" in folder else (pafs.LocalFileSystem(), folder)
        name, out, n = f"{root}/_{uuid.uuid4().hex}", None, 0
        for batch in batches:
            x = matrix(batch.column(1)).astype("<f4") if len(batch) else []
            if not len(x):
                continue
            if out is None:
                fs.create_dir(root, recursive=True)
                out = fs.open_output_stream(name)
            table = np.empty(len(x), np.dtype([("dim", "<i4"), ("x", "<f4", (x.shape[1],))]))
            table["dim"], table["x"] = x.shape[1], x
            out.write(table.tobytes())
            n += len(x)
        if out is not None:
            out.close()
            part = TaskContext.get().partitionId()
            fs.move(name, f"{root}/part-{part:06d}.fvecs")
            yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "path": [f"part-{part:06d}.fvecs"], "n": pa.array([n], pa.int64())})

    ranged = df.select("id", "vec").repartitionByRange(files, "id").sortWithinPartitions("id")
    rows = sorted(ranged.mapInArrow(write, "part int, path string, n long").collect())  # one row per file
    first = np.cumsum([0, *(r["n"] for r in rows)]).tolist()
    return df.sparkSession.createDataFrame([(r["path"], first[i], r["n"]) for i, r in enumerate(rows)], "path string, first long, n long")


def read_vector_files(spark: SparkSession, path: str, with_path: bool = False) -> DataFrame:
    """Length-prefixed float records (int32 dimension, then float32 values), ids by position in a file."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, content in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                raw = content.as_buffer()
                if not len(raw):
                    continue
                (dim,) = struct.unpack("<i", raw[:4].to_pybytes())
                table = np.frombuffer(raw, np.dtype([("dim", "<i4"), ("x", "<f4", (dim,))]))
                if (table["dim"] != dim).any():
                    raise ValueError(f"{name}: records of different lengths")
                for lo in range(0, len(table), 1024):
                    x = table["x"][lo : lo + 1024].astype(np.float64)
                    offsets = pa.array(np.arange(len(x) + 1, dtype=np.int32) * dim)
                    rows = [pa.array(np.arange(lo, lo + len(x))), pa.ListArray.from_arrays(offsets, pa.array(x.ravel()))]
                    yield pa.RecordBatch.from_arrays([*rows, pa.array([name] * len(x))] if with_path else rows, ["id", "vec", "path"] if with_path else ["id", "vec"])

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(run, f"{_VEC}, path string" if with_path else _VEC)


def vector_record(vec: list[float]) -> bytes:
    """One record of a vector file."""
    return struct.pack(f"<i{len(vec)}f", len(vec), *vec)
