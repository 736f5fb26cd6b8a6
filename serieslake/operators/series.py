"""From tables to equal-length series."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import summaries as S
from ..session import cut, stored

BLOCK = 4096


def matrix(column: pa.Array, n: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, n)


def lists(x: np.ndarray, kind: pa.DataType | None = None) -> pa.Array:
    """A list column from the rows of a matrix, without Python objects."""
    kind = kind or pa.float64()
    flat = pa.array(np.ascontiguousarray(x).ravel(), kind)
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1], pa.int32()), flat)


def map_series(df: DataFrame, fn, n: int) -> DataFrame:
    """Applies a row-matrix function to ``values``, keeping series_id."""

    def run(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), lists(fn(matrix(b.column(1), n)))], names=["series_id", "values"])

    return df.select("series_id", "values").mapInArrow(run, "series_id bigint, values array<double>")


def from_array(df: DataFrame, id_col: str, array_col: str, scale: float = 1.0) -> DataFrame:
    return df.select(F.col(id_col).cast("bigint").alias("series_id"), F.transform(array_col, lambda x: x.cast("double") * F.lit(scale)).alias("values"))


def cumsum(df: DataFrame, n: int) -> DataFrame:
    """Walks from steps: the running sum of each array."""
    return map_series(df, lambda x: np.cumsum(x, axis=1), n)


def cumsum_column(values: Column) -> Column:
    """The running sum as an expression; for parity tests, the kernel is faster."""
    return F.aggregate(values, F.array().cast("array<double>"), lambda a, x: F.concat(a, F.array(F.coalesce(F.try_element_at(a, F.lit(-1)), F.lit(0.0)) + x)))


def from_rows(df: DataFrame, key: str, order: str, value: str, n: int) -> DataFrame:
    """The first n rows of each key in order, as one series; keys with fewer rows give none."""
    got = df.groupBy(F.col(key).cast("bigint").alias("series_id")).agg(F.sort_array(F.collect_list(F.struct(F.col(order).alias("o"), F.col(value).cast("double").alias("v")))).alias("r"))
    return got.where(F.size("r") >= n).select("series_id", F.transform(F.slice("r", 1, n), lambda x: x["v"]).alias("values"))


def slots(df: DataFrame, key: str, slot: Column, value: Column, n: int, fill: str = "zero") -> DataFrame:
    """One series a key from sums by slot 0..n-1; sums are rounded to four places, empty slots are filled
    by zero, by the last value ("forward") or on a line between neighbours ("linear")."""
    sums = df.select(F.col(key).cast("bigint").alias("series_id"), slot.cast("int").alias("slot"), value.alias("v")).where(F.col("slot").between(0, n - 1)).groupBy("series_id", "slot").agg(F.round(F.sum("v"), 4).alias("v"))
    held = sums.groupBy("series_id").agg(F.collect_list("slot").alias("s"), F.collect_list("v").alias("v"))

    def fill_rows(batches):
        for b in batches:
            out = np.zeros((b.num_rows, n))
            for i, (s, v) in enumerate(zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True)):
                out[i, s] = v
                if fill != "zero":
                    known = np.array(sorted(s))
                    values = out[i, known]
                    if fill == "linear":
                        out[i] = np.interp(np.arange(n), known, values)
                    else:
                        at = np.searchsorted(known, np.arange(n), side="right") - 1
                        out[i] = np.where(at >= 0, values[np.maximum(at, 0)], 0.0)
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), lists(out)], names=["series_id", "values"])

    return held.mapInArrow(fill_rows, "series_id bigint, values array<double>")


def dense_index(df: DataFrame, *order: str) -> DataFrame:
    """Adds ``i``, the position in the global order from 0: a range partitioning, counts of the
    partitions, and a row number inside each. The order is written down first, so a retried task agrees."""
    ranged = cut(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_p", F.spark_partition_id()))
    counts = ranged.groupBy("_p").agg(F.count(F.lit(1)).alias("n")).orderBy("_p").collect()  # one row a partition
    starts, at = [], 0
    for r in counts:
        starts.append((r["_p"], at))
        at += r["n"]
    offsets = df.sparkSession.createDataFrame(starts or [(0, 0)], "_p int, _at bigint")
    rank = F.row_number().over(Window.partitionBy("_p").orderBy(*order))
    return ranged.withColumn("_r", rank).join(F.broadcast(offsets), "_p").withColumn("i", F.col("_at") + F.col("_r") - 1).drop("_p", "_r", "_at")


def prefix_sum(df: DataFrame, index: str, value: str, block: int = BLOCK) -> DataFrame:
    """Adds ``running``: sums of blocks first, a window over the few blocks, then a window inside each block."""
    blocked = df.withColumn("_b", F.floor(F.col(index) / block))
    sums = blocked.groupBy("_b").agg(F.sum(value).alias("_s"))
    before = sums.withColumn("_before", F.coalesce(F.sum("_s").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))).drop("_s")
    inner = F.sum(value).over(Window.partitionBy("_b").orderBy(index).rowsBetween(Window.unboundedPreceding, 0))
    return blocked.withColumn("_in", inner).join(before, "_b").withColumn("running", F.col("_before") + F.col("_in")).drop("_b", "_in", "_before")


def windows(df: DataFrame, index: str, value: str, n: int, step: int = 1, block: int = BLOCK) -> DataFrame:
    """Sliding windows of n rows by dense index; series_id is the index of the last row. Blocks of rows
    carry the n-1 rows before them, so there is no global window; a third of a block's rows are halo at most
    when block is three times n or more."""
    block = max(block, n)
    spread = _with_halo(df, index, value, n, block)
    frame = Window.partitionBy("_b").orderBy("i").rowsBetween(-(n - 1), 0)
    got = spread.withColumn("values", F.collect_list("v").over(frame)).where((F.floor(F.col("i") / block) == F.col("_b")) & (F.size("values") == n))
    return got.where((F.col("i") - (n - 1)) % step == 0).select(F.col("i").cast("bigint").alias("series_id"), "values")


def _with_halo(df: DataFrame, index: str, value: str, n: int, block: int) -> DataFrame:
    """(i, v, _b): the rows of each block and the n-1 before it."""
    return df.select(F.col(index).alias("i"), F.col(value).cast("double").alias("v")).withColumn("_b", F.explode(F.when((F.col("i") + n - 1) >= (F.floor(F.col("i") / block) + 1) * block, F.array(F.floor(F.col("i") / block), F.floor(F.col("i") / block) + 1)).otherwise(F.array(F.floor(F.col("i") / block)))))


@dataclass(frozen=True)
class Raw:
    """A collection that is held once, from which steps take the values they need: whole or by id, not normalised.

    ``units`` (unit, ids, at, points) hold some series each: the i-th of ``ids`` is the n points from place ``at[i]`` on, so
    windows share their points. ``unit_of`` gives the unit from an id.
    """

    frame: DataFrame  # series_id, values
    units: DataFrame
    unit_of: Callable[[str], Column]

    @cached_property
    def points(self) -> int:
        return self.units.agg(F.sum(F.size("points"))).first()[0] or 0


def plain(df: DataFrame) -> Raw:
    """Each series is a unit of its own."""
    units = df.select(F.col("series_id").alias("unit"), F.array("series_id").alias("ids"), F.array(F.lit(0)).alias("at"), F.col("values").alias("points"))
    return Raw(df, units, F.col)


def window_blocks(df: DataFrame, index: str, value: str, n: int, step: int = 1, block: int = BLOCK) -> Raw:
    """The windows of :func:`windows`, of values that are never null. Written down are the points, each about once; a window
    is cut out where it is read, and only if its values are asked for."""
    block = max(block, n)
    held = _with_halo(df, index, value, n, block).groupBy(F.col("_b").cast("bigint").alias("unit")).agg(F.sort_array(F.collect_list(F.struct("i", "v"))).alias("p")).where("unit is not null")
    end = lambda s: F.get("p", s + (n - 1))["i"]
    places = F.when(F.size("p") >= n, F.filter(F.sequence(F.lit(0), F.size("p") - n), lambda s: (F.floor(end(s) / block) == F.col("unit")) & ((end(s) - (n - 1)) % step == 0))).otherwise(F.array().cast("array<int>"))
    held = held.withColumn("at", places).select("unit", F.transform("at", lambda s: end(s).cast("bigint")).alias("ids"), "at", F.transform("p", lambda x: x["v"]).alias("points"))
    units = stored(held)
    each = units.select("points", F.explode(F.arrays_zip("ids", "at")).alias("w"))
    return Raw(each.select(F.col("w.ids").alias("series_id"), F.slice("points", F.col("w.at") + 1, n).alias("values")), units, lambda c: F.floor(F.col(c) / block))


def key_windows(df: DataFrame, key: str, order: list[str], value: str, id_col: str, n: int, step: int = 1) -> DataFrame:
    """Sliding windows inside each key; series_id is the id of the last row."""
    w = Window.partitionBy(key).orderBy(*order)
    got = df.withColumn("values", F.collect_list(F.col(value).cast("double")).over(w.rowsBetween(-(n - 1), 0))).withColumn("_r", F.row_number().over(w))
    return got.where((F.size("values") == n) & ((F.col("_r") - n) % step == 0)).select(F.col(id_col).cast("bigint").alias("series_id"), "values")


def normalise(df: DataFrame, kind: str, n: int) -> DataFrame:
    """kind: z, minmax, detrend (straight line taken off), difference (first point kept as 0), none."""

    def minmax(x):
        lo, hi = x.min(axis=1, keepdims=True), x.max(axis=1, keepdims=True)
        return np.where(hi > lo, (x - lo) / np.where(hi > lo, hi - lo, 1.0), 0.0)

    def detrend(x):
        t = np.arange(n) - (n - 1) / 2
        slope = (x * t).sum(axis=1, keepdims=True) / (t * t).sum()
        return x - x.mean(axis=1, keepdims=True) - slope * t

    kinds = {"z": S.znorm_rows, "minmax": minmax, "detrend": detrend, "difference": lambda x: np.diff(x, axis=1, prepend=x[:, :1]), "none": lambda x: x}
    return map_series(df, kinds[kind], n)


def to_long(df: DataFrame) -> DataFrame:
    return df.select("series_id", F.posexplode("values").alias("pos", "value"))


def to_wide(df: DataFrame, n: int) -> DataFrame:
    return from_rows(df, "series_id", "pos", "value", n)


# --- stand-in collections on the given tables ---------------------------------------------------


def walk64(embeddings: DataFrame) -> DataFrame:
    """Random walks: the running sum over eight times each embedding."""
    return cumsum(from_array(embeddings, "vec_id", "embedding", 8.0), 64)


def vec64(embeddings: DataFrame) -> DataFrame:
    return from_array(embeddings, "vec_id", "embedding")


def signal_points(events: DataFrame) -> DataFrame:
    """(i, running): the running sum of value - 50 in event order, six places."""
    points = events.select(F.col("event_id").alias("i"), (F.coalesce("value", F.lit(0.0)) - 50.0).alias("v"))
    return prefix_sum(points, "i", "v").select("i", F.round("running", 6).alias("running"))


def signal256(events: DataFrame, step: int = 1) -> DataFrame:
    return windows(signal_points(events), "i", "running", 256, step)


def signal256_blocks(events: DataFrame, step: int = 1) -> Raw:
    return window_blocks(signal_points(events), "i", "running", 256, step)


def user32(events: DataFrame, step: int = 1) -> DataFrame:
    return key_windows(events, "user_id", ["ts", "event_id"], "value", "event_id", 32, step)


def parts64(lineitem: DataFrame) -> DataFrame:
    """Cumulated monthly revenue of each part over 64 months from January 1995."""
    month = (F.year("l_shipdate") - 1995) * 12 + F.month("l_shipdate") - 1
    return cumsum(slots(lineitem, "l_partkey", month, F.col("l_extendedprice") * (1 - F.col("l_discount")), 64), 64)


def daily256(orders: DataFrame, step: int = 1) -> DataFrame:
    """Windows over the running sum of daily order totals less their mean; days without orders count zero."""
    day = orders.groupBy(F.to_date("o_orderdate").alias("day")).agg(F.round(F.sum("o_totalprice"), 4).alias("total"))
    ends = day.agg(F.min("day").alias("a"), F.max("day").alias("b"))
    grid = ends.select(F.explode(F.sequence("a", "b")).alias("day"))
    filled = grid.join(day, "day", "left").select("day", F.coalesce("total", F.lit(0.0)).alias("total"))
    mean = filled.agg(F.avg("total").alias("mean"))
    dense = filled.crossJoin(F.broadcast(mean)).crossJoin(F.broadcast(ends)).select(F.datediff("day", "a").alias("i"), (F.col("total") - F.col("mean")).alias("v"))
    return windows(prefix_sum(dense, "i", "v").select("i", F.round("running", 4).alias("running")), "i", "running", 256, step)


def split_outside(series: DataFrame, count: int, queries: int = 100) -> tuple[DataFrame, DataFrame]:
    """(collection, queries): every (count/queries)-th id leaves the collection and becomes a query."""
    m = max(1, count // queries)
    asked = F.col("series_id") % m == m - 1
    return series.where(~asked), series.where(asked).select(F.col("series_id").alias("query_id"), "values")
