"""Embedding near-duplicates by collision-counting projections.

Unit vectors are projected on many random lines. Two vectors whose cosine reaches the bound lie
within a known distance, so on a line each lies in the other's window with a known probability; the number of
lines where they do is binomial. Pairs that reach the count which linked pairs reach with probability
``RECALL`` are verified by the cosine in double precision.

Lines that are sorted alone tell little: a window holds a large share of all vectors. So a pair is counted once it
shares a cell of some band, a band being several lines cut at steps of ``STEP``. The lines of a band grow with
the logarithm of a label's vectors, so that a cell holds about ``CROWD`` unrelated pairs a vector however many there are, and the bands
so that a linked pair shares one with probability ``RECALL``. Keys of cells are counted first, on narrow rows; vectors go
only to cells with two or more. Cells of more than ``BLOCK`` are dealt out as pairs of blocks.

A cell hands on, for each of its vectors, the number of links that no earlier band has counted and the smallest vector
it is connected with there: no pairs, however dense. Equal vectors of a label are collapsed first and counted, so copies cost
nothing. Vectors that are null, empty, zero or hold null or non-finite components, and rows of a null label, link with
nothing. Lengths need not agree: vectors of different length don't link. Rows of a null id have no part in links. Repeated
rows count as links of each other; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, cut

COSINE, RECALL, LINES, WINDOW = 0.98, 0.9999, 48, 1.6
STEP, CROWD, BLOCK, PAIRS = 6.0, 0.25, 2048, 1 << 19


def needed(lines: int = LINES, recall: float = RECALL) -> int:
    """The collision count that a pair at the bound reaches with the asked probability."""
    p = math.erf(WINDOW / math.sqrt(2))
    miss, k = 0.0, -1
    while miss <= 1 - recall:
        k += 1
        miss += math.comb(lines, k) * p**k * (1 - p) ** (lines - k)
    return k


def lines(dim: int, n: int = LINES, seed: int = 0) -> np.ndarray:
    """Random directions, scaled so that a pair at the bound differs by a standard normal."""
    spread = math.sqrt(2 - 2 * COSINE)
    return np.random.default_rng((dim, seed)).standard_normal((dim, n)) / spread


def same_cell(spread: float) -> float:
    """How often two values that differ by a normal of this spread fall into one step of a randomly shifted line."""
    r = STEP / spread
    return math.erf(r / math.sqrt(2)) - 2 / (math.sqrt(2 * math.pi) * r) * (1 - math.exp(-r * r / 2))


def bands(vectors: int) -> tuple[int, int]:
    """(lines of a band, bands) for a label of so many vectors."""
    apart, linked = same_cell(math.sqrt(2 / (2 - 2 * COSINE))), same_cell(1.0)
    width = max(2, math.ceil(math.log(max(vectors, 2) / CROWD) / -math.log(apart)))
    return width, math.ceil(math.log(1 - RECALL) / math.log1p(-(linked**width)))


def keys_of(unit: np.ndarray, label: np.ndarray, shape: tuple[int, int]) -> np.ndarray:
    """(vectors, bands) hashes of the cells."""
    width, n = shape
    dim = unit.shape[1]
    shift = np.random.default_rng((dim, 2)).random(width * n) * STEP
    cells = np.floor((unit @ lines(dim, width * n, 1) + shift) / STEP).astype(np.int64).astype(np.uint64).reshape(-1, n, width)
    h = np.broadcast_to((label.view(np.uint64) ^ np.uint64(dim))[:, None], cells.shape[:2]) + np.arange(n, dtype=np.uint64)[None] * np.uint64(0xD6E8FEB86659FD93)
    for k in range(width):
        h = (h ^ cells[:, :, k]) * np.uint64(0x9E3779B97F4A7C15)
        h = h ^ h >> np.uint64(29)
    return h.view(np.int64)


def _unit(column: pa.Array) -> np.ndarray:
    v = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)
    return v / np.linalg.norm(v, axis=1, keepdims=True)


def by_length(b: pa.RecordBatch, column: int):
    """Rows of a batch whose vectors have one length."""
    sizes = b.column(column).value_lengths().to_numpy(zero_copy_only=False)
    for dim in np.unique(sizes).tolist():
        yield b.take(pa.array(np.flatnonzero(sizes == dim)))


def pairs_of(sizes: np.ndarray):
    """(a, b) with a < b: all pairs of rows of one group, for groups that lie one after the other; in portions."""
    begin = np.cumsum(sizes) - sizes
    row = np.arange(sizes.sum())
    after = np.repeat(begin + sizes, sizes) - row - 1
    cuts = np.searchsorted(np.cumsum(after), np.arange(PAIRS, after.sum() + PAIRS, PAIRS), side="left") + 1
    for lo, hi in zip([0, *cuts[:-1].tolist()], cuts.tolist(), strict=True):
        n = after[lo:hi]
        a = np.repeat(row[lo:hi], n)
        yield a, a + 1 + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)


def linked(group: np.ndarray, side: np.ndarray, crossed: np.ndarray, label: np.ndarray, unit: np.ndarray):
    """(a, b) rows of one group that reach the count and the cosine; rows are sorted by group. In crossed groups only rows
    of different sides are compared."""
    proj = unit @ lines(unit.shape[1])
    allowed = LINES - needed()
    sizes = np.diff(np.concatenate([np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]])), [len(group)]]))
    for a, b in pairs_of(sizes):
        keep = (label[a] == label[b]) & ~(crossed[a] & (side[a] == side[b]))
        a, b = a[keep], b[keep]
        misses = np.zeros(len(a), dtype=np.int32)
        for line in range(LINES):
            misses += np.abs(proj[a, line] - proj[b, line]) > WINDOW
            if line % 4 == 3:
                keep = misses <= allowed
                a, b, misses = a[keep], b[keep], misses[keep]
        keep = np.einsum("ij,ij->i", unit[a], unit[b]) >= COSINE
        yield a[keep], b[keep]


def found_in(rows: pa.Table, shape: tuple[int, int]) -> pa.RecordBatch:
    """(rep, near, root): links of each vector that no earlier band counts, and the smallest vector it is connected with."""
    key = np.stack([rows.column(c).to_numpy() for c in ("cell", "i", "j")], axis=1)
    group = np.cumsum(np.concatenate([[False], (key[1:] != key[:-1]).any(axis=1)]))
    side, crossed = rows.column("side").to_numpy(), rows.column("crossed").to_numpy(zero_copy_only=False)
    label, rep, copies, band = (rows.column(c).to_numpy() for c in ("lab", "rep", "copies", "band"))
    unit = _unit(rows.column("vector").combine_chunks())
    near, root = np.zeros(len(rep), dtype=np.int64), np.arange(len(rep))
    order = np.argsort(rep, kind="stable")
    rank = np.empty(len(rep), dtype=np.int64)
    rank[order] = np.arange(len(rep))
    low = rank.copy()
    for a, b in linked(group, side, crossed, label, unit):
        if not len(a):
            continue
        used, place = np.unique(np.concatenate([a, b]), return_inverse=True)
        keys = keys_of(unit[used], label[used], shape)
        first = (keys[place[: len(a)]] == keys[place[len(a) :]]).argmax(axis=1) == band[a]
        np.add.at(near, a[first], copies[b[first]])
        np.add.at(near, b[first], copies[a[first]])
        while True:
            least = np.minimum(low[a], low[b])
            before = low.copy()
            np.minimum.at(low, a, least)
            np.minimum.at(low, b, least)
            if (low == before).all():
                break
    root = rep[order[low]]
    some = (near > 0) | (root < rep)
    return pa.RecordBatch.from_arrays([pa.array(rep[some]), pa.array(near[some]), pa.array(root[some])], names=["rep", "near", "root"])


def links(distinct: DataFrame, shape: tuple[int, int]) -> DataFrame:
    """(rep, near, root) by cell, from (lab, vector, rep, copies) of distinct vectors."""

    def spread(batches):
        for batch in batches:
            for b in by_length(batch, 1):
                keys = keys_of(_unit(b.column(1)), b.column(0).to_numpy(), shape)
                n = keys.shape[1]
                yield pa.RecordBatch.from_arrays([pa.array(keys.ravel()), pa.array(np.tile(np.arange(n, dtype=np.int32), len(keys))), b.column(2).take(pa.array(np.repeat(np.arange(len(keys)), n)))], names=["cell", "band", "rep"])

    def compare(batches):
        held, size = [], 0

        def settle(parts):
            table = pa.Table.from_batches(parts)
            lengths = pc.list_value_length(table.column("vector")).to_numpy()
            for dim in np.unique(lengths).tolist():
                yield found_in(table.take(pa.array(np.flatnonzero(lengths == dim))), shape)

        for b in batches:
            if not b.num_rows:
                continue
            key = np.stack([b.column(0).to_numpy(), b.column(1).to_numpy(), b.column(2).to_numpy()], axis=1)
            last = int(np.flatnonzero((key != key[-1]).any(axis=1)).max(initial=-1)) + 1  # the last group may go on
            if held and size + last >= 2 * BLOCK and last:
                yield from settle([*held, b.slice(0, last)])
                held, size, b = [], 0, b.slice(last)
            elif held and size >= 2 * BLOCK and not last and tuple(key[0]) != at:
                yield from settle(held)
                held, size = [], 0
            held.append(b)
            size += b.num_rows
            at = tuple(key[-1])
        if held:
            yield from settle(held)

    kind = distinct.schema["vector"].dataType.simpleString()
    keys = cut(distinct.select("lab", "vector", "rep").mapInArrow(spread, "cell bigint, band int, rep bigint"))
    crowds = keys.groupBy(F.col("cell").alias("_cell")).agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    alive = keys.join(crowds, F.col("cell") == F.col("_cell")).withColumn("blocks", F.ceil(F.col("n") / BLOCK).cast("int"))
    alive = alive.withColumn("side", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    placed = alive.select("cell", F.least("side", "other").alias("i"), F.greatest("side", "other").alias("j"), "side", (F.col("side") != F.col("other")).alias("apart"), "band", "rep")
    # a block meets itself in (i, i), so rows of a pair of blocks are compared across only
    full = placed.join(distinct.withColumnRenamed("rep", "_rep"), F.col("rep") == F.col("_rep")).select("cell", "i", "j", "side", (F.col("i") != F.col("j")).alias("crossed"), "band", "rep", "lab", "copies", F.col("vector").cast(kind).alias("vector"))
    return full.repartition("cell", "i", "j").sortWithinPartitions("cell", "i", "j").mapInArrow(compare, "rep bigint, near bigint, root bigint")


def usable(vector: str = "embedding", label: str = "label"):
    v = F.col(vector)
    sound = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.col(label).isNotNull() & F.coalesce(sound & F.exists(v, lambda x: x != 0), F.lit(False))


def near_duplicates(rows: DataFrame, vec_id: str = "vec_id", vector: str = "embedding", label: str = "label") -> DataFrame:
    """vec_id, n_links, component_id, kept of every row."""
    every = rows.select(F.col(vec_id).alias("vec_id"), F.col(vector).alias("vector"), F.col(label).alias("label"))
    good = usable("vector", "label") & F.col("vec_id").isNotNull()
    # copies become one vector with its smallest id and their number
    reps = cut(every.where(good).groupBy("label", "vector").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("copies")))
    most = reps.groupBy("label").count().agg(F.max("count")).first()[0] or 0
    got = cut(links(reps.select(F.xxhash64("label").alias("lab"), "vector", F.col("rep").cast("bigint").alias("rep"), "copies"), bands(most)))
    roots = components(got.select(F.col("rep").alias("a"), F.col("root").alias("b")))
    near = got.groupBy(F.col("rep").alias("a")).agg(F.sum("near").alias("near"))
    named = reps.join(near, F.col("rep") == F.col("a"), "left").join(roots, F.col("rep") == F.col("node"), "left")
    named = named.select(F.col("label").alias("l"), F.col("vector").alias("v"), (F.col("copies") - 1 + F.coalesce("near", F.lit(0))).alias("links"), F.coalesce("root", "rep").alias("root"))
    out = every.withColumn("good", good).join(named, F.col("good") & (F.col("label") == F.col("l")) & (F.col("vector") == F.col("v")), "left")
    return out.select("vec_id", F.coalesce("links", F.lit(0)).cast("bigint").alias("n_links"), F.coalesce("root", "vec_id").alias("component_id"), F.coalesce(F.coalesce("root", "vec_id") == F.col("vec_id"), F.lit(False)).alias("kept"))
