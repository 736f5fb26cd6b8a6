"""Helpers the corpus operators share: Arrow batch mapping, lineage cuts, connected components."""

from __future__ import annotations

import hashlib
import tempfile
from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Rows of one Arrow batch; texts are whole, so a batch is bounded by rows and by Spark's bytes per batch.
BATCH_ROWS = 2000


def sha(data: bytes | str) -> str:
    return hashlib.sha256(data.encode("utf-8", "surrogatepass") if isinstance(data, str) else data).hexdigest()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tuned(spark: SparkSession) -> SparkSession:
    """Small Arrow batches: whole texts may be long, so a worker holds few of them at once."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    return spark


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir; one of our own only on a single machine that names none."""
    if spark.sparkContext.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and (not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster")):
            raise RuntimeError("name a folder that all executors share in spark.checkpoint.dir")
        spark.sparkContext.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoints-"))
    return spark.sparkContext.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """Cuts the lineage by a reliable checkpoint in the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def apart(docs: DataFrame, own: Sequence[str] = ("doc_id", "text")) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """``docs`` with all columns but ``own`` under neutral names, so that no name of ours clashes, and the way back."""
    names = docs.columns
    inner = [n if n in own else f"_other{i}" for i, n in enumerate(names)]
    return docs.toDF(*inner), lambda out: out.select(*(F.col(a).alias(b) for a, b in zip(inner, names, strict=True)))


def map_batches(df: DataFrame, keep: Sequence[str], inputs: Sequence[str], fields: Sequence[T.StructField], fn: Callable[[], Callable[..., list[list]]]) -> DataFrame:
    """One output row per input row. ``fn()`` runs once a task and gives a function from the
    lists of ``inputs`` to the lists of ``fields``; the ``keep`` columns pass as Arrow arrays,
    so that integer ids with nulls stay exact."""
    schema = T.StructType([*(df.schema[k] for k in keep), *fields])
    types = [pa_type(f.dataType) for f in fields]
    names = [*keep, *(f.name for f in fields)]
    n_keep, n_in = len(keep), len(inputs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = fn()
        for b in batches:
            out = work(*(b.column(n_keep + i).to_pylist() for i in range(n_in)))
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(n_keep)), *(pa.array(x, type=t) for x, t in zip(out, types, strict=True))], names=names)

    cols = [F.col(k) for k in keep] + [F.col(c).alias(f"_in{i}") for i, c in enumerate(inputs)]
    return df.select(*cols).mapInArrow(run, schema)


def pa_type(t: T.DataType) -> pa.DataType:
    if isinstance(t, T.StructType):
        return pa.struct([pa.field(f.name, pa_type(f.dataType)) for f in t.fields])
    simple = {"bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string(), "boolean": pa.bool_(), "binary": pa.binary()}
    if isinstance(t, T.ArrayType):
        return pa.list_(pa_type(t.elementType))
    return simple[t.simpleString()]


def squeeze(*parts: np.ndarray, level: int = 3) -> bytes:
    """Arrays without negative numbers in one compressed string, by planes of bytes. Signed integers are taken for mostly
    small: they get one byte each, and four planes more for those from 255 on."""
    out = []
    for x in parts:
        if x.dtype.kind == "u":
            planes = np.ascontiguousarray(x).view(np.uint8).reshape(-1, x.itemsize).T
        else:
            large = x[x >= 255].astype("<u4").view(np.uint8).reshape(-1, 4)
            planes = [np.minimum(x, 255).astype(np.uint8), *large.T]
        packed = [zstandard.compress(np.ascontiguousarray(p).tobytes(), level) for p in planes]
        out.append(len(packed).to_bytes(1, "little") + b"".join(len(p).to_bytes(8, "little") + p for p in packed))
    return b"".join(out)


def unsqueeze(data: bytes) -> list[np.ndarray]:
    out, at = [], 0
    while at < len(data):
        planes, n, at = [], data[at], at + 1
        for _ in range(n):
            size = int.from_bytes(data[at : at + 8], "little")
            planes.append(np.frombuffer(zstandard.decompress(data[at + 8 : at + 8 + size]), np.uint8))
            at += 8 + size
        if n == 5:
            x = planes[0].astype(np.int64)
            x[x == 255] = np.stack(planes[1:], axis=1).view("<u4").ravel()
        else:
            x = np.stack(planes, axis=1).view(f"<u{n}").ravel()
        out.append(x)
    return out


def gathered(batches, settle):
    """Rows come sorted by bucket in column 0; settle(bucket, its rows as lists of the other columns) runs for each."""
    held, key = None, None
    for b in batches:
        for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
            if row[0] != key:
                if held:
                    yield from settle(key, held)
                held, key = [], row[0]
            held.append(row[1:])
    if held:
        yield from settle(key, held)


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Connected components of undirected edges by alternating star contraction.

    Returns (node, root) for every node that has an edge to another; root is the smallest node
    reachable. Each round is two joins on narrow rows and a reliable checkpoint; only a round that
    changes nothing ends it. The number of rounds grows with the logarithm of the longest path.
    Null ends and loops are ignored; no edges give no rows.
    """
    e = edges.select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo")).where("hi <> lo").distinct()
    e, seen = cut(e), None
    while True:
        # every node hands its larger neighbours to its smallest one
        both = e.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(e.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).where("hi <> lo").distinct()
        # then all its smaller neighbours and itself
        low = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(low, "hi").select(F.explode(F.array(F.struct(F.col("hi").alias("hi"), F.col("m").alias("lo")), F.struct(F.col("lo").alias("hi"), F.col("m").alias("lo")))).alias("x")).select("x.hi", "x.lo").where("hi <> lo").distinct()
        e = cut(small)
        now = e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first()
        if now == seen:
            break
        seen = now
    return e.groupBy(F.col("hi").alias("node")).agg(F.min("lo").alias("root"))
