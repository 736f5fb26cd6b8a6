"""Scans with schema assertion, other formats, raw float files, generators, and the side output for bad rows."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

SERIES = T.StructType([T.StructField("series_id", T.LongType()), T.StructField("values", T.ArrayType(T.DoubleType()))])


def load(spark: SparkSession, sf_dir: str, name: str, fmt: str = "parquet", schema: T.StructType | None = None) -> DataFrame:
    """A table of the folder. A given schema is asserted for Parquet and applied for text formats."""
    path = f"{sf_dir}/{name}.{fmt}"
    if fmt == "parquet":
        df = spark.read.parquet(path)
        if schema is not None:
            have = dict(df.dtypes)
            wrong = [f.name for f in schema.fields if have.get(f.name) != f.dataType.simpleString()]
            if wrong:
                raise ValueError(f"{name}: columns missing or of another type: {wrong}")
        return df
    reader = spark.read.format("json" if fmt == "jsonl" else fmt)
    if schema is not None:
        reader = reader.schema(schema)
    return reader.load(path, **({"header": True} if fmt == "csv" else {}))


def validate_series(series: DataFrame, n: int) -> tuple[DataFrame, DataFrame]:
    """(sound, rejected with a reason): wrong length, null array, null or non-finite points, null id."""
    v = F.col("values")
    reason = (
        F.when(F.col("series_id").isNull(), "null id")
        .when(v.isNull(), "null array")
        .when(F.size(v) != n, "wrong length")
        .when(F.exists(v, lambda x: x.isNull()), "null point")
        .when(F.exists(v, lambda x: F.isnan(x) | (F.abs(x) == float("inf"))), "non-finite point")
    )
    marked = series.withColumn("reason", reason)
    return marked.where("reason is null").drop("reason"), marked.where("reason is not null")


def write_f32(series: DataFrame, path: str, n: int) -> None:
    """Rows of little-endian float32 in id order, as base64 lines, which every Spark file system can write; ids are not kept."""

    def pack(batches):
        for b in batches:
            v = b.column(0).flatten().to_numpy(zero_copy_only=False)
            yield pa.RecordBatch.from_arrays([pa.array([v.astype("<f4").tobytes()])], names=["content"])

    packed = series.orderBy("series_id").select("values").mapInArrow(pack, "content binary")
    packed.select(F.regexp_replace(F.base64("content"), "[\r\n]", "").alias("value")).write.mode("overwrite").text(path)


def read_f32(spark: SparkSession, path: str, n: int, raw: bool = False) -> DataFrame:
    """(file, line, row, values) of the files of :func:`write_f32`, or of raw binary files of float32 rows
    (``raw``, one line a file; files of a few hundred MB at most)."""

    def unpack(batches):
        for b in batches:
            for name, at, data in zip(*(c.to_pylist() for c in b.columns), strict=True):
                v = np.frombuffer(data, dtype="<f4").reshape(-1, n).astype(np.float64)
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(v)), pa.array([at] * len(v), pa.int64()), pa.array(range(len(v)), pa.int64()), pa.array(list(v), pa.list_(pa.float64()))], names=["file", "line", "row", "values"])

    if raw:
        lines = spark.read.format("binaryFile").load(path).select(F.col("path").alias("file"), F.lit(0).cast("bigint").alias("line"), "content")
        return lines.mapInArrow(unpack, "file string, line bigint, row bigint, values array<double>")
    lines = spark.read.text(path).select(F.input_file_name().alias("file"), F.monotonically_increasing_id().alias("line"), F.unbase64("value").alias("content"))
    return lines.mapInArrow(unpack, "file string, line bigint, row bigint, values array<double>")


def gaussian_rows(ids: np.ndarray, n: int, seed: int) -> np.ndarray:
    """(ids, n) standard normal numbers that depend on nothing but seed, id and place (Box-Muller on hashes), so a retried task repeats them."""
    with np.errstate(over="ignore"):
        at = ids.astype(np.uint64)[:, None] * np.uint64(n) + np.arange(n, dtype=np.uint64)[None]
        u, v = (_unit_hash(at, seed * 2 + k) for k in (0, 1))
    return np.sqrt(-2 * np.log(np.maximum(u, 1e-300))) * np.cos(2 * np.pi * v)


def random_walks(spark: SparkSession, count: int, n: int, seed: int = 42, partitions: int | None = None) -> DataFrame:
    """``count`` walks of Gaussian(0,1) steps."""
    ids = spark.range(0, count, 1, partitions) if partitions else spark.range(count)

    def walk(batches):
        for b in batches:
            steps = gaussian_rows(b.column(0).to_numpy(), n, seed)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(list(np.cumsum(steps, axis=1)), pa.list_(pa.float64()))], names=["series_id", "values"])

    return ids.mapInArrow(walk, SERIES)


def _unit_hash(x: np.ndarray, salt: int) -> np.ndarray:
    x = (x + np.uint64(salt + 1)) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return ((x ^ (x >> np.uint64(31))) >> np.uint64(11)).astype(np.float64) / (1 << 53)


def noisy_queries(series: DataFrame, sigma: float, count: int, seed: int = 42) -> DataFrame:
    """(query_id, values): ``count`` members in hash order with N(0, sigma^2) added to each z-normalised point."""
    from ..functions.summaries import znorm_rows

    picked = series.withColumn("_h", F.xxhash64(F.lit(seed), "series_id")).orderBy("_h", "series_id").limit(count)

    def add(batches):
        for b in batches:
            if b.num_rows:
                x = znorm_rows(np.stack(b.column(1).to_numpy(zero_copy_only=False)))
                x = x + sigma * gaussian_rows(b.column(0).to_numpy(), x.shape[1], seed)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(list(x), pa.list_(pa.float64()))], names=["query_id", "values"])

    return picked.select("series_id", "values").mapInArrow(add, "query_id bigint, values array<double>")


def materialize(df: DataFrame) -> None:
    """Runs a plan for its time alone."""
    df.write.format("noop").mode("overwrite").save()
