"""Query answering: a first answer, pruning by bounds, ordered refinement with true distances.

There is no shared best-so-far in Spark. Each wave starts from a broadcast value that is never under
the final distance, and each task lowers its own copy with distances of real members, so a stale
value costs work, never an answer. Equal distances go to the smaller id.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..config import IndexConfig
from ..functions import summaries as S
from ..session import apart, cut, small
from .index import SeriesIndex, assign, normal
from .series import dense_index, matrix

MAX_QUERIES = 10_000
#: Bytes of points that one task holds beside its pairs.
UNIT_BYTES = 64 << 20
#: Share of all pairs from which on a scan of the values beats fetching them by pair.
SCAN_SHARE = 0.2
#: Most series of a block that one task of the self-join holds.
SELF_BLOCK = 50_000
ANSWER = "query_id bigint, series_id bigint, dist double"


@dataclass
class Queries:
    """A query set of bounded size, prepared on the driver and broadcast."""

    ids: np.ndarray
    values: np.ndarray
    paa: np.ndarray
    words: np.ndarray

    @classmethod
    def of(cls, queries: DataFrame, cfg: IndexConfig) -> Queries:
        rows = queries.select("query_id", "values").limit(MAX_QUERIES + 1).toArrow()
        if rows.num_rows > MAX_QUERIES:
            raise ValueError(f"more than {MAX_QUERIES} queries: ask in batches")
        order = np.argsort(rows.column(0).to_numpy(), kind="stable")
        x = matrix(rows.column(1).combine_chunks(), cfg.n)[order] if rows.num_rows else np.zeros((0, cfg.n))
        x = S.znorm_rows(x) if cfg.normalise == "z" else x
        paa = S.paa_rows(x, cfg.w)
        return cls(rows.column(0).to_numpy()[order], x, paa, S.symbol_rows(paa, cfg.bits))


def lowest(lb: np.ndarray, query: np.ndarray, most: int) -> np.ndarray:
    """Places of the ``most`` least bounds of each query."""
    order = np.lexsort((lb, query))
    rank = np.arange(len(order)) - np.searchsorted(query[order], query[order])
    return order[rank < most]


def leaf_bounds(nodes: DataFrame, q: Queries, bsf: np.ndarray, cfg: IndexConfig, key: str = "leaf_id", heads: int | None = None) -> DataFrame:
    """(query_id, key, lb) of the nodes whose bound doesn't exceed a query's best-so-far; with ``heads`` of each batch
    of nodes the so many least ones a query only."""
    shared = nodes.sparkSession.sparkContext.broadcast((q.ids, q.paa, bsf))

    def run(batches):
        ids, paa, bsf = shared.value
        for b in batches:
            if not b.num_rows or not len(ids):
                continue
            lb = S.gap_rows(paa, matrix(b.column(1), cfg.w), matrix(b.column(2), cfg.w), cfg.n)
            i, k = np.nonzero(lb * (1 - cfg.slack) <= bsf[:, None])
            if heads is not None:
                keep = lowest(lb[i, k], i, heads)
                i, k = i[keep], k[keep]
            yield pa.RecordBatch.from_arrays([pa.array(ids[i]), b.column(0).take(pa.array(k)), pa.array(lb[i, k])], names=["query_id", key, "lb"])

    return nodes.select(key, "lo", "hi").mapInArrow(run, f"query_id bigint, {key} {dict(nodes.dtypes)[key]}, lb double")


def prune(index: SeriesIndex, q: Queries, bsf: np.ndarray, levelwise: bool = False) -> DataFrame:
    """Candidate leaves (query_id, leaf_id, lb). ``levelwise`` goes down from the roots and never looks below a pruned node."""
    if not levelwise:
        return leaf_bounds(index.leaves, q, bsf, index.cfg)
    nodes = index.nodes.withColumn("node", F.concat_ws(":", "bucket", "path"))
    live, depth, parts = nodes.where("depth = 0"), 0, []
    while not live.isEmpty():
        kept = cut(leaf_bounds(live, q, bsf, index.cfg, "node"))
        parts.append(kept.join(live.where("is_leaf and n_items > 0").select("node", "leaf_id"), "node").select("query_id", "leaf_id", "lb"))
        # a child is looked at for all queries if any query keeps its parent; its own bound settles each
        inner = kept.select("node").distinct()
        depth += 1
        below = nodes.where(F.col("depth") == depth).withColumn("up", F.concat(F.col("bucket").cast("string"), F.lit(":"), F.substring("path", 1, depth - 1)))
        live = below.join(inner.withColumnRenamed("node", "up"), "up", "left_semi").select(*nodes.columns)
    out = parts[0] if parts else leaf_bounds(index.leaves, q, bsf, index.cfg).limit(0)
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def enqueue(candidates: DataFrame, queues: int, by: str | Column = "leaf_id") -> DataFrame:
    """Adds queue_id: candidates are dealt to the queues by their leaf, so that a queue reads its leaves' values once."""
    return candidates.withColumn("queue_id", F.pmod(F.xxhash64(by), F.lit(queues)).cast("int"))


def deal(candidates: DataFrame, index: SeriesIndex) -> DataFrame:
    """The candidates in queues by what holds their values: their leaf, or their unit of the collection."""
    return enqueue(candidates, index.cfg.queues, "leaf_id" if index.raw is None else index.raw.unit_of("series_id"))


def beside(pairs: DataFrame, index: SeriesIndex, order: list[str], act, schema: str) -> DataFrame:
    """``act`` over narrow pairs (queue_id, query_id, series_id, lb) in ``order`` where the values are in the collection. Pairs and
    units meet in as many tasks a queue as hold UNIT_BYTES of points each: units come first and are held, so a value
    is neither moved nor written once for each pair. ``act``: takes (pairs' batch, places -> values) batches."""
    raw, cfg, n = index.raw, index.cfg, index.cfg.n
    subs = max(1, -(-8 * raw.points // (cfg.queues * UNIT_BYTES)))
    to = (F.col("queue_id") * subs + F.pmod(F.xxhash64(F.col("unit"), F.lit(1)), F.lit(subs))).cast("int")
    of = pairs.withColumn("unit", raw.unit_of("series_id").cast("bigint"))
    asked = of.select("unit").distinct()
    units = enqueue(raw.units.withColumn("unit", F.col("unit").cast("bigint")).join(small(cut(asked)), "unit", "left_semi"), cfg.queues, "unit")
    null = lambda t: F.lit(None).cast(t)
    first = units.select(to.alias("to"), F.lit(0).alias("kind"), "queue_id", null("bigint").alias("query_id"), null("bigint").alias("series_id"), null("double").alias("lb"), "ids", "at", "points")
    then = of.select(to.alias("to"), F.lit(1).alias("kind"), "queue_id", "query_id", "series_id", "lb", null("array<bigint>").alias("ids"), null("array<int>").alias("at"), null("array<double>").alias("points"))
    rows = first.unionByName(then).repartitionById(cfg.queues * subs, "to").sortWithinPartitions("to", "kind", *order)

    def run(batches):
        held, tables = [], {}

        def fed():
            for b in batches:
                kind, to = b.column(1).to_numpy(), b.column(0).to_numpy()
                cuts = [0, *(np.flatnonzero((np.diff(to) != 0) | (np.diff(kind) != 0)) + 1).tolist(), len(to)] if b.num_rows else [0]
                for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                    part = b.slice(lo, hi - lo)
                    if tables.get("to") != to[lo]:
                        held.clear()
                        tables.clear()
                        tables["to"] = to[lo]
                    if kind[lo] == 0:
                        ids, points = part.column(6).flatten().to_numpy(), part.column(8).flatten().to_numpy(zero_copy_only=False)
                        counts, sizes = (part.column(k).value_lengths().to_numpy() for k in (6, 8))
                        at = part.column(7).flatten().to_numpy().astype(np.int64) + np.repeat(np.cumsum(sizes) - sizes, counts)
                        held.append((ids.copy(), at, points.astype(np.float64)))
                        continue
                    if "ids" not in tables:
                        shift = np.cumsum([0, *(len(p) for _, _, p in held)])
                        ids, at, points = np.concatenate([i for i, _, _ in held]), np.concatenate([a + s for (_, a, _), s in zip(held, shift, strict=False)]), np.concatenate([p for _, _, p in held])
                        held.clear()
                        by = np.argsort(ids, kind="stable")
                        tables.update(ids=ids[by], at=at[by], points=points)
                    starts = tables["at"][np.searchsorted(tables["ids"], part.column(4).to_numpy())]
                    points = tables["points"]
                    yield part, lambda s, e, starts=starts, points=points: normal(points[starts[s:e, None] + np.arange(n)], cfg)

        yield from act(fed())

    return rows.mapInArrow(run, schema)


def order_queues(queued: DataFrame, queues: int) -> DataFrame:
    """One array for each queue, sorted by query and bound."""
    return queued.repartition(queues, "queue_id").sortWithinPartitions("queue_id", "query_id", "lb", "series_id")


def asked_leaves(leaves: DataFrame, checked: bool = False) -> DataFrame:
    """(leaf_id, asked): each candidate leaf once, with its queries. ``checked``: written down, and few are marked as :func:`small`."""
    if "asked" in leaves.columns:
        return leaves
    got = leaves.groupBy("leaf_id").agg(F.collect_list("query_id").alias("asked"))
    return small(cut(got)) if checked else got


def _item_bounds(index: SeriesIndex, q: Queries, bsf: np.ndarray, leaves: DataFrame | None, heads: int | None = None) -> DataFrame:
    """(query_id, series_id, leaf_id, lb): members of candidate leaves, or of all, whose own bound survives. Reads no raw
    values. With ``heads`` of each batch of members the so many least ones a query only."""
    cfg = index.cfg
    shared = index.by_leaf.sparkSession.sparkContext.broadcast((q.ids, q.paa, bsf))
    rows = index.by_leaf.select("leaf_id", "series_id", "word")
    if leaves is not None:
        rows = apart(rows).join(asked_leaves(leaves), "leaf_id").select("leaf_id", "series_id", "word", "asked")

    def run(batches):
        ids, paa, bsf = shared.value
        for b in batches:
            if not b.num_rows or not len(ids):
                continue
            word = b.column(2).flatten().to_numpy().reshape(-1, cfg.w)
            lo, hi = S.intervals(word, np.full_like(word, cfg.bits), cfg.bits)
            if b.num_columns == 4:
                rows = np.repeat(np.arange(b.num_rows), np.diff(b.column(3).offsets.to_numpy()))
                which = np.searchsorted(ids, b.column(3).flatten().to_numpy())
            else:
                rows, which = np.divmod(np.arange(b.num_rows * len(ids)), len(ids))
            for at in range(0, len(rows), 1 << 18):
                r, k = rows[at : at + (1 << 18)], which[at : at + (1 << 18)]
                gap = np.maximum(np.maximum(lo[r] - paa[k], paa[k] - hi[r]), 0.0)
                lb = np.sqrt(cfg.n / cfg.w * (gap * gap).sum(axis=1))
                keep = np.flatnonzero(lb * (1 - cfg.slack) <= bsf[k])
                if heads is not None:
                    keep = keep[lowest(lb[keep], k[keep], heads)]
                yield pa.RecordBatch.from_arrays([pa.array(ids[k[keep]]), b.column(1).take(pa.array(r[keep])), b.column(0).take(pa.array(r[keep])), pa.array(lb[keep])], names=["query_id", "series_id", "leaf_id", "lb"])

    return rows.mapInArrow(run, "query_id bigint, series_id bigint, leaf_id bigint, lb double")


def with_values(pairs: DataFrame, index: SeriesIndex) -> DataFrame:
    """``pairs`` with the values of their members. Pairs are narrow: where the caller has found them :func:`small`, they go to
    where the values are, and values are shuffled only for more."""
    if index.raw is not None:
        return pairs.join(apart(index.values), "series_id")
    return pairs.join(apart(index.by_leaf.select("leaf_id", "series_id", "values")), ["leaf_id", "series_id"])


def refine(queued: DataFrame, index: SeriesIndex, q: Queries, bsf: np.ndarray, k: int = 1) -> DataFrame:
    """(query_id, series_id, dist) from queues of (queue_id, query_id, series_id, leaf_id, lb), each consumed from its least
    bound on: distances lower the queue's own best-so-far, and the first bound above it ends the query in that queue."""
    n, slack = index.cfg.n, index.cfg.slack
    shared = queued.sparkSession.sparkContext.broadcast((q.ids, q.values, bsf))

    def consume(parts):
        ids, values, bsf = shared.value
        at, best, over = None, np.zeros(0), False
        for b, rows in parts:
            key = np.stack([b["queue_id"].to_numpy(), b["query_id"].to_numpy()], axis=1)
            lb = b["lb"].to_numpy()
            cuts = np.concatenate([[0], np.flatnonzero((key[1:] != key[:-1]).any(axis=1)) + 1, [len(key)]])
            for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                if at != tuple(key[lo]):
                    at, best, over = tuple(key[lo]), np.zeros(0), False
                which = int(np.searchsorted(ids, at[1]))
                for s in range(lo, hi, 32):
                    limit = min(bsf[which], best[k - 1] if len(best) >= k else np.inf)
                    e = min(s + 32, hi)
                    e = s + int(np.searchsorted(lb[s:e] * (1 - slack), limit, side="right"))
                    if over or e == s:
                        over = True
                        break
                    d = S.distances(rows(s, e), np.broadcast_to(values[which], (e - s, n)), np.full(e - s, limit * (1 + slack) if np.isfinite(limit) else np.inf))
                    got = np.isfinite(d)
                    best = np.sort(np.concatenate([best, d[got]]))[:k]
                    if got.any():
                        yield pa.RecordBatch.from_arrays([b["query_id"].slice(s, e - s).filter(pa.array(got)), b["series_id"].slice(s, e - s).filter(pa.array(got)), pa.array(d[got])], names=["query_id", "series_id", "dist"])

    if index.raw is not None:
        return beside(queued, index, ["queue_id", "query_id", "lb", "series_id"], consume, ANSWER)
    # how many queues there are is a property of the rows, so no column is read for it twice
    rows = order_queues(with_values(queued, index).select("queue_id", "query_id", "series_id", "lb", "values"), index.cfg.queues)

    def run(batches):
        def taken(b):
            x = []

            def rows(s, e):
                if not x:
                    x.append(matrix(b.column(4), n))
                return x[0][s:e]

            return rows

        yield from consume((b, taken(b)) for b in batches if b.num_rows)

    return rows.mapInArrow(run, ANSWER)


def _true_distances(pairs: DataFrame, index: SeriesIndex, q: Queries, bsf: np.ndarray) -> DataFrame:
    """(query_id, series_id, dist) of pairs within the best-so-far; others are given up early."""
    shared = pairs.sparkSession.sparkContext.broadcast((q.ids, q.values, bsf))
    n, slack = index.cfg.n, index.cfg.slack

    def measure(parts):
        ids, values, bsf = shared.value
        for b, rows in parts:
            for s in range(0, b.num_rows, 4096):
                e = min(s + 4096, b.num_rows)
                query, series = b["query_id"].slice(s, e - s), b["series_id"].slice(s, e - s)
                k = np.searchsorted(ids, query.to_numpy())
                limit = bsf[k]
                d = S.distances(rows(s, e), values[k], np.where(np.isfinite(limit), limit * (1 + slack), np.inf))
                keep = np.isfinite(d)
                yield pa.RecordBatch.from_arrays([query.filter(pa.array(keep)), series.filter(pa.array(keep)), pa.array(d[keep])], names=["query_id", "series_id", "dist"])

    if index.raw is not None:
        return beside(deal(pairs.withColumn("lb", F.lit(0.0)), index), index, ["query_id", "series_id"], measure, ANSWER)

    def run(batches):
        yield from measure((b, lambda s, e, b=b: matrix(b.column(2).slice(s, e - s), n)) for b in batches if b.num_rows)

    return with_values(pairs, index).select("query_id", "series_id", "values").mapInArrow(run, ANSWER)


def top_k(answers: DataFrame, k: int) -> DataFrame:
    """The k nearest of each query with rank; ties by id. Repeated answers count once."""
    w = Window.partitionBy("query_id").orderBy("dist", "series_id")
    return answers.groupBy("query_id", "series_id").agg(F.min("dist").alias("dist")).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def _kth(best: DataFrame, q: Queries, k: int) -> np.ndarray:
    out = np.full(len(q.ids), np.inf)
    for r in best.where(F.col("rank") == k).select("query_id", "dist").collect():  # at most MAX_QUERIES rows
        out[np.searchsorted(q.ids, r["query_id"])] = r["dist"]
    return out


def home_leaves(index: SeriesIndex, q: Queries, spark) -> DataFrame:
    """(query_id, leaf_id): the leaf that a query's own path leads to, or the leaf of least bound where that one is
    missing or empty. Only for the latter are bounds computed, and of each batch of leaves one a query goes on."""
    rows = list(zip(q.ids.tolist(), q.words.tolist(), S.bucket_rows(q.words, index.cfg.bits).tolist(), strict=True))
    asked = spark.createDataFrame(rows, "series_id bigint, word array<int>, bucket int")
    led = assign(asked.select("bucket", "word").distinct(), asked, index.nodes, index.cfg)
    led = cut(led.join(index.leaves.select("leaf_id"), "leaf_id", "left_semi").select(F.col("series_id").alias("query_id"), "leaf_id"))
    known = {r[0] for r in led.select("query_id").collect()}  # at most MAX_QUERIES rows
    bsf = np.where(np.isin(q.ids, list(known)), -1.0, np.inf)
    if not np.isinf(bsf).any():
        return led
    least = leaf_bounds(index.leaves, q, bsf, index.cfg, heads=1).groupBy("query_id").agg(F.min_by("leaf_id", F.struct("lb", "leaf_id")).alias("leaf_id"))
    return led.unionByName(least)


def seed(index: SeriesIndex, q: Queries, how: str, k: int = 1) -> DataFrame:
    """First answers: the members of each query's own leaf ("leaf"), the members of least bound ("best_lb"), or none."""
    none = np.full(len(q.ids), np.inf)
    spark = index.nodes.sparkSession
    if how == "none" or not len(q.ids):
        return spark.createDataFrame([], ANSWER)
    if how == "leaf":
        members = small(home_leaves(index, q, spark)).join(apart(index.by_leaf.select("leaf_id", "series_id")), "leaf_id")
        return _true_distances(small(cut(members)), index, q, none)
    leaves = leaf_bounds(index.leaves, q, none, index.cfg, heads=4)
    return _true_distances(small(cut(_item_bounds(index, q, none, leaves, heads=k).select("query_id", "series_id", "leaf_id"))), index, q, none)


def knn(index: SeriesIndex, queries: DataFrame, k: int = 1, levelwise: bool = False, first_wave: int = 32) -> DataFrame:
    """(query_id, series_id, dist, rank): the exact k nearest members of each query.

    A first wave takes the members of least bounds of each batch, which brings the best-so-far close to its end; the
    second wave bounds all members against it and refines what is left. Where bounds rule out little, the values are scanned.
    """
    q = Queries.of(queries, index.cfg)
    best = cut(top_k(seed(index, q, index.cfg.seed_how, k), k))
    bsf = _kth(best, q, k)
    if index.cfg.waves != "one" and len(q.ids):
        near = asked_leaves(leaf_bounds(index.leaves, q, bsf, index.cfg, heads=first_wave), True)
        heads = small(cut(_item_bounds(index, q, bsf, near, heads=first_wave).select("query_id", "series_id", "leaf_id")))
        best = cut(top_k(best.select("query_id", "series_id", "dist").unionByName(_true_distances(heads, index, q, bsf)), k))
        bsf = _kth(best, q, k)
    items = cut(_item_bounds(index, q, bsf, asked_leaves(prune(index, q, bsf, levelwise), True)))
    alive, members = items.count(), index.leaves.agg(F.sum("n_items")).first()[0] or 0
    if alive > SCAN_SHARE * members * len(q.ids):
        got = _scan(index.values, q, bsf, k, index.cfg.n, index.raw is not None and index.cfg.normalise == "z")
    else:
        got = refine(small(deal(items, index)), index, q, bsf, k)
    return cut(top_k(best.select("query_id", "series_id", "dist").unionByName(got), k))


def nn1(index: SeriesIndex, queries: DataFrame, **options) -> DataFrame:
    return knn(index, queries, 1, **options).drop("rank")


def approx_nn(index: SeriesIndex, queries: DataFrame) -> DataFrame:
    """The best member of each query's own leaf: a first answer, not always the nearest."""
    return top_k(seed(index, Queries.of(queries, index.cfg), "leaf"), 1).drop("rank")


def range_search(index: SeriesIndex, queries: DataFrame, eps: float) -> DataFrame:
    """All members within ``eps`` of each query."""
    q = Queries.of(queries, index.cfg)
    bsf = np.full(len(q.ids), eps)
    items = _item_bounds(index, q, bsf, prune(index, q, bsf))
    return _true_distances(items.select("query_id", "series_id", "leaf_id"), index, q, bsf).where(F.col("dist") <= eps)


def _copies(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(one row for each value: leaf_id, series_id, values, n; answers of series that have copies), so that many copies of one
    series cost no pairs among them."""
    sound = rows.where(~F.exists("values", lambda x: x.isNull() | F.isnan(x)))
    reps = cut(sound.groupBy("values").agg(F.min("leaf_id").alias("leaf_id"), F.min("series_id").alias("series_id"), F.count(F.lit(1)).alias("n")))
    many = reps.where("n > 1").select("values", F.col("series_id").alias("least"))
    of = cut(apart(sound).join(many, "values").select("series_id", "least"))
    second = of.where("series_id <> least").groupBy("least").agg(F.min("series_id").alias("second"))
    found = of.join(second, "least").select(F.col("series_id").alias("query_id"), F.when(F.col("series_id") == F.col("least"), F.col("second")).otherwise(F.col("least")).alias("series_id"), F.lit(0.0).alias("dist"))
    return reps, found


class _Block:
    """A run of series in leaf order with their best answers so far."""

    def __init__(self, place: np.ndarray, ids: np.ndarray, asks: np.ndarray, x: np.ndarray):
        self.x, self.place, self.ids = x[asks], place[asks], ids[asks]
        self.best, self.who = np.full(len(self.x), np.inf), np.zeros(len(self.x), dtype=np.int64)
        self.square = np.einsum("ij,ij->i", self.x, self.x)
        at = np.flatnonzero(asks)
        for step in (*range(1, 9), *range(-8, 0)):  # neighbours in leaf order give the first answers
            mine = np.flatnonzero((at + step >= 0) & (at + step < len(x)))
            self.take(mine, S.distances(self.x[mine], x[at[mine] + step]), ids[at[mine] + step])

    def take(self, rows: np.ndarray, d: np.ndarray, ids: np.ndarray) -> None:
        order = np.lexsort((ids, d, rows))
        rows, d, ids = rows[order], d[order], ids[order]
        first = np.flatnonzero(np.diff(rows, prepend=-1))
        rows, d, ids = rows[first], d[first], ids[first]
        better = (d < self.best[rows]) | (d == self.best[rows]) & (ids < self.who[rows])
        self.best[rows[better]], self.who[rows[better]] = d[better], ids[better]

    def look(self, place: np.ndarray, ids: np.ndarray, x: np.ndarray, tile: int = 1024) -> None:
        """Compares with other series: a matrix product tells which pairs may improve, and those are computed directly."""
        for b in range(0, len(x), tile):
            y = x[b : b + tile]
            theirs = np.column_stack([y, np.ones(len(y)), np.einsum("ij,ij->i", y, y)]).T
            for a in range(0, len(self.x), tile):
                mine = slice(a, a + tile)
                with np.errstate(invalid="ignore"):
                    over = self.square[mine] - (self.best[mine] ** 2 * (1 + 1e-6) + 1e-6)
                    r, j = np.nonzero(np.column_stack([-2 * self.x[mine], np.maximum(over, -1e300), np.ones(len(over))]) @ theirs <= 0)
                other = self.place[a + r] != place[b + j]
                r, j = a + r[other], j[other]
                for k in range(0, len(r), 65536):
                    self.take(r[k : k + 65536], S.distances(self.x[r[k : k + 65536]], y[j[k : k + 65536]]), ids[b + j[k : k + 65536]])

    def answers(self) -> pa.RecordBatch:
        known = np.isfinite(self.best)
        return pa.RecordBatch.from_arrays([pa.array(self.ids[known]), pa.array(self.who[known]), pa.array(self.best[known])], names=["query_id", "series_id", "dist"])


def self_nn(index: SeriesIndex, block: int = SELF_BLOCK) -> DataFrame:
    """The nearest other member of every series, by one join of the collection with itself.

    Series in leaf order are cut into blocks of equal size; a task holds one block, gets its first answers from
    neighbouring leaves and then looks at all others as they come, those of near blocks first. Copies are settled before.
    """
    n, spark = index.cfg.n, index.nodes.sparkSession
    reps, found = _copies(index.by_leaf.select("leaf_id", "series_id", "values"))
    placed = cut(dense_index(reps, "leaf_id", "series_id").select("i", "series_id", (F.col("n") == 1).alias("asks"), "values"))
    total = placed.count()
    size = max(1, min(block, -(-total // int(spark.conf.get("spark.sql.shuffle.partitions")))))
    blocks = max(1, -(-total // size))
    home = F.floor(F.col("i") / size).cast("int")
    sent = placed.withColumn("to", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select("to", F.abs(home - F.col("to")).alias("off"), "i", "series_id", "asks", "values")
    dealt = sent.repartitionById(blocks, "to").sortWithinPartitions("to", "off", "i")

    def run(batches):
        at, own, held = None, [], None
        for b in batches:
            if not b.num_rows:
                continue
            to, off, place, ids, asks = (b.column(k).to_numpy(zero_copy_only=False) for k in range(5))
            x = matrix(b.column(5), n)
            cuts = [0, *(np.flatnonzero((np.diff(to) != 0) | ((off[1:] == 0) != (off[:-1] == 0))) + 1).tolist(), len(to)]
            for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                if at != to[lo]:
                    if own:
                        held = _settled(own)
                    if held is not None:
                        yield held.answers()
                    at, own, held = to[lo], [], None
                part = place[lo:hi], ids[lo:hi], asks[lo:hi], x[lo:hi]
                if off[lo] == 0:
                    own.append(part)
                    continue
                if own:
                    held, own = _settled(own), []
                held.look(part[0], part[1], part[3])
        if own:
            held = _settled(own)
        if held is not None:
            yield held.answers()

    return found.unionByName(dealt.mapInArrow(run, ANSWER))


def _settled(parts: list[tuple[np.ndarray, ...]]) -> _Block:
    """A block from its rows, compared with itself."""
    place, ids, asks, x = map(np.concatenate, zip(*parts, strict=True))
    held = _Block(place, ids, asks, x)
    held.look(place, ids, x)
    return held


def _scan(series: DataFrame, q: Queries, bsf: np.ndarray, k: int, n: int, normalise: bool = False) -> DataFrame:
    """(query_id, series_id, dist) over all series, the k best of each batch: distances are filtered by a matrix product and
    computed directly where they may be under the best-so-far, which each task lowers for itself."""
    shared = series.sparkSession.sparkContext.broadcast((q.ids, q.values, bsf))

    def run(batches):
        ids, values, bsf = shared.value
        for b in batches:
            if not b.num_rows or not len(ids):
                continue
            x = matrix(b.column(1), n)
            x = S.znorm_rows(x) if normalise else x
            r, j = S.block_filter(x, values, bsf) if np.isfinite(bsf).all() else map(np.ravel, np.indices((len(x), len(ids))))
            parts = [S.distances(x[r[a : a + 65536]], values[j[a : a + 65536]]) for a in range(0, len(r), 65536)]
            d = np.concatenate(parts) if parts else np.zeros(0)
            order = np.lexsort((d, j))
            r, j, d = r[order], j[order], d[order]
            rank = np.arange(len(j)) - np.searchsorted(j, j)
            last = np.minimum(np.searchsorted(j, j) + k - 1, len(j) - 1)
            keep = (rank < k) | (d <= d[last]) & (j[last] == j)
            r, j, d = r[keep], j[keep], d[keep]
            full = np.bincount(j, minlength=len(ids)) >= k
            kth = np.where(full, 0.0, np.inf)
            np.maximum.at(kth, j, d)
            bsf = np.minimum(bsf, kth)
            yield pa.RecordBatch.from_arrays([pa.array(ids[j]), b.column(0).take(pa.array(r)), pa.array(d)], names=["query_id", "series_id", "dist"])

    return series.select("series_id", "values").mapInArrow(run, ANSWER)


def brute_knn(series: DataFrame, queries: DataFrame, k: int, cfg: IndexConfig) -> DataFrame:
    """Ground truth: every distance."""
    q = Queries.of(queries, cfg)
    return top_k(_scan(series, q, np.full(len(q.ids), np.inf), k, cfg.n, cfg.normalise == "z"), k)


def scan_knn(index: SeriesIndex, queries: DataFrame, k: int = 1) -> DataFrame:
    """No tree: all members' bounds, then distances of the survivors."""
    q = Queries.of(queries, index.cfg)
    none = np.full(len(q.ids), np.inf)
    first = _true_distances(_item_bounds(index, q, none, None, heads=k).select("query_id", "series_id", "leaf_id"), index, q, none)
    bsf = _kth(cut(top_k(first, k)), q, k)
    items = _item_bounds(index, q, bsf, None)
    return top_k(_true_distances(items.select("query_id", "series_id", "leaf_id"), index, q, bsf), k)
