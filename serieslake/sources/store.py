"""Indexes on disk: Parquet under numbered versions, made current by one atomic create of a manifest."""

from __future__ import annotations

import json
import uuid
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession

from ..config import IndexConfig
from ..operators.index import SeriesIndex, insert_batch


def _fs(spark: SparkSession, path: str):
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()), spark._jvm.org.apache.hadoop.fs.Path


def _manifest(spark: SparkSession, path: str) -> dict | None:
    fs, at = _fs(spark, path)
    if not fs.exists(at(path)):
        return None
    names = [s.getPath().getName() for s in fs.listStatus(at(path))]
    versions = sorted(int(n.removeprefix("_manifest-v")) for n in names if n.startswith("_manifest-v"))
    if not versions:
        return None
    stream = fs.open(at(f"{path}/_manifest-v{versions[-1]}"))
    text = bytes(spark._jvm.org.apache.commons.io.IOUtils.toByteArray(stream)).decode()
    stream.close()
    return json.loads(text)


class LostRace(RuntimeError):
    """Another writer has published the version first."""


def save(index: SeriesIndex, path: str, batches: tuple[int, ...] = (), after: int | None = None) -> int:
    """Writes a new version into a folder of its own and publishes it by an exclusive create of its manifest. A writer that
    loses the race, or whose version doesn't follow ``after``, raises and has touched nothing that others read."""
    spark = index.nodes.sparkSession
    old = _manifest(spark, path)
    last = old["version"] if old else 0
    if after is not None and last != after:
        raise LostRace(path)
    version, folder = last + 1, f"data-{uuid.uuid4()}"
    for name in ("summaries", "nodes", "by_leaf"):
        getattr(index, name).write.parquet(f"{path}/{folder}/{name}")
    fs, at = _fs(spark, path)
    try:
        out = fs.create(at(f"{path}/_manifest-v{version}"), False)
    except Exception as e:
        fs.delete(at(f"{path}/{folder}"), True)
        raise LostRace(path) from e
    out.write(bytearray(json.dumps({"version": version, "folder": folder, "batches": sorted(batches), "config": asdict(index.cfg)}).encode()))
    out.close()
    return version


def load(spark: SparkSession, path: str) -> SeriesIndex:
    return _load(spark, path, _manifest(spark, path))


def _load(spark: SparkSession, path: str, m: dict | None) -> SeriesIndex:
    if m is None:
        raise FileNotFoundError(path)
    parts = {n: spark.read.parquet(f"{path}/{m['folder']}/{n}") for n in ("summaries", "nodes", "by_leaf")}
    return SeriesIndex(IndexConfig(**m["config"]), **parts)


def append(spark: SparkSession, path: str, series: DataFrame, batch_id: int) -> bool:
    """Adds a batch of series once; False for a batch that the manifest names already. A writer whose leaves were
    replaced meanwhile reads the new version and inserts again."""
    while True:
        m = _manifest(spark, path)
        if m is None:
            raise FileNotFoundError(path)
        if batch_id in m["batches"]:
            return False
        try:
            save(insert_batch(_load(spark, path, m), series), path, (*m["batches"], batch_id), after=m["version"])
            return True
        except LostRace:
            continue
