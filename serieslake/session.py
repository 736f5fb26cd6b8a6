"""Session helpers: sizes that are checked before a broadcast, and the folder all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of a query set or node table that one broadcast may hold.
BROADCAST_ROWS = 200_000
#: Bytes of a row group of series. A task holds a row group as a whole to write and to read it, and reads it through buffers
#: outside the heap, as large as the group, that its thread keeps.
ROW_GROUP = 16 << 20


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder the cluster names; one of our own only on a single machine that names none."""
    if spark.sparkContext.getCheckpointDir() is None:
        named, master = spark.conf.get("spark.checkpoint.dir", None), spark.sparkContext.master
        if not named and (not master.startswith("local") or master.startswith("local-cluster")):
            raise RuntimeError("name a folder that all executors share in spark.checkpoint.dir")
        spark.sparkContext.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoints-"))
    return spark.sparkContext.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """Ends the lineage with a reliable checkpoint, so that a lost executor costs no rebuild of the steps before."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def in_columns(df: DataFrame, path: str) -> None:
    """Writes Parquet in row groups of ROW_GROUP bytes."""
    df.write.mode("overwrite").option("parquet.block.size", ROW_GROUP).option("compression", "zstd").parquet(path)


def stored(df: DataFrame) -> DataFrame:
    """As :func:`cut`, in columns: for wide rows of which later steps read a few narrow columns."""
    path = f"{shared_folder(df.sparkSession)}/stored-{uuid.uuid4()}"
    in_columns(df, path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """A broadcast hint if ``df`` has at most ``rows`` rows, else ``df`` itself; reads one row more than that at most."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def apart(df: DataFrame) -> DataFrame:
    """``df`` for a join that shuffles it, unless the other side is :func:`small`. Spark takes an array for one element, so
    it would broadcast series at a hundredth of their size, and AQE doesn't take that back."""
    return df.hint("merge")


def ship(spark: SparkSession) -> None:
    """Makes this package importable on executors that weren't started with it on their path; once a session."""
    import os
    import zipfile

    sc = spark.sparkContext
    if getattr(sc, "_serieslake_shipped", False):
        return
    root = os.path.dirname(os.path.abspath(__file__))
    top = os.path.dirname(root)
    name = os.path.join(tempfile.mkdtemp(), "serieslake.zip")
    with zipfile.ZipFile(name, "w") as z:
        for folder, _, files in os.walk(root):
            for f in files:
                if f.endswith(".py"):
                    z.write(os.path.join(folder, f), os.path.relpath(os.path.join(folder, f), top))
    sc.addPyFile(name)
    sc._serieslake_shipped = True


def shipped(f):
    """A query that ships the package before it runs."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return f(spark, sf_dir)

    return run
