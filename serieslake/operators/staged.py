"""Query answering as four helped stages: collection, buckets, tree, queues.

Each stage is a traversal of the stage before, cut into parts: chunks of the collection, pieces of buckets, runs of
leaves, queues of candidates. All go through the same ledger, so a late or dead worker in any stage is helped,
and the next stage begins when all parts are done, whoever did them.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import IndexConfig
from ..functions import summaries as S
from ..session import apart, cut, small, stored
from . import index as X
from . import search as Q
from .index import SeriesIndex
from .parts import Fault, Stage, run_parts
from .series import matrix

STAGES = ("summarize", "tree", "prune", "refine")
TREE = "bucket int, path string, n_items bigint"
TOP = 3


@dataclass
class Run:
    """Answers with what was done for them: the index, and each stage with its ledger."""

    answers: DataFrame | None = None
    index: SeriesIndex | None = None
    stages: dict[str, Stage] = field(default_factory=dict)
    ledgers: dict[str, DataFrame] = field(default_factory=dict)

    def ledger(self) -> DataFrame:
        out = None
        for name, df in self.ledgers.items():
            df = df.withColumn("stage", F.lit(name))
            out = df if out is None else out.unionByName(df)
        return out


def part_of(column: str, parts: int):
    return F.pmod(F.xxhash64(column), F.lit(parts)).cast("int")


def heads(words: DataFrame, cfg: IndexConfig, top: int = TOP) -> DataFrame:
    """(bucket, word, head): the first bits of a word's path, by which buckets fall into pieces."""
    return words.select("bucket", "word", F.substring(X.path_bits(F.col("word"), cfg), 1, min(top, cfg.max_depth)).alias("head"))


def pieces(keyed: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(bucket, path, n_items) of the nodes of each piece, its head included."""

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        head = pdf["head"].iloc[0]
        nodes = X.subtree(np.stack(pdf.word.to_numpy()), np.ones(len(pdf), dtype=np.int64), cfg, head, len(head))
        return pd.DataFrame({"bucket": int(pdf.bucket.iloc[0]), "path": [p for p, _ in nodes], "n_items": [n for _, n in nodes]})

    return keyed.groupBy("bucket", "head").applyInPandas(build, TREE)


def assemble(deep: DataFrame, cfg: IndexConfig, top: int = TOP) -> DataFrame:
    """The forest from its pieces: nodes above are counted from the heads, and a node is there if its ancestors split."""
    top = min(top, cfg.max_depth)
    deep = deep.select("bucket", "path", "n_items")
    ends = deep.where(F.length("path") == top)
    upper = ends.select("bucket", F.explode(F.transform(F.sequence(F.lit(0), F.lit(top - 1)), lambda d: F.substring("path", F.lit(1), d))).alias("path"), "n_items").groupBy("bucket", "path").agg(F.sum("n_items").alias("n_items"))
    counted = stored(upper.unionByName(deep))
    splits = counted.where((F.col("n_items") > cfg.theta) & (F.length("path") < cfg.max_depth))
    children = splits.select("bucket", F.explode(F.array(F.concat("path", F.lit("0")), F.concat("path", F.lit("1")))).alias("path"))
    return counted.where("path = ''").unionByName(children.join(apart(counted), ["bucket", "path"], "left").select("bucket", "path", F.coalesce("n_items", F.lit(0)).alias("n_items")))


def staged(run: Run, name: str, spark, parts: int, make: Callable[..., DataFrame], fault: Fault | None, groups: int = 1, **options) -> DataFrame:
    """Runs a stage and returns its elements, each once. ``make(part, group=None)``."""
    stage = Stage(spark, name, groups=groups)
    run.stages[name] = stage
    run.ledgers[name] = run_parts(stage, range(parts), make, fault=fault, make_group=make if groups > 1 else None, **options)
    return stage.read()


def summaries_stage(run: Run, series: DataFrame, cfg: IndexConfig, fault: Fault | None = None, keep_values: bool = True, **options) -> DataFrame:
    """Summaries, with values unless told otherwise, laid out by bucket inside each part. Chunks and their groups, by which helpers go, are ranges
    of ids of about equal size, so that a source sorted by id reads little more than the range."""
    k, m = cfg.k_chunks, cfg.m_groups if cfg.levels > 1 else 1
    edges = series.approxQuantile("series_id", [i / (k * m) for i in range(1, k * m)], 0.005)  # k * m - 1 numbers, or none

    def make(part: int, group: int | None = None) -> DataFrame:
        lo, hi = (part * m, part * m + m) if group is None else (part * m + group, part * m + group + 1)
        mine = series
        if edges:
            mine = mine.where(F.col("series_id") >= edges[lo - 1]) if lo else mine
            mine = mine.where(F.col("series_id") < edges[hi - 1]) if hi < k * m else mine
        elif lo:
            mine = mine.where(F.lit(False))
        return X.summarize(mine, cfg, keep_values).sortWithinPartitions("bucket")

    return staged(run, "summarize", series.sparkSession, k, make, fault, m, backoff_factor=cfg.backoff_factor, **options).select("series_id", "paa", "word", "bucket", *["values"] * keep_values)


def bucket_slices(stage: Stage) -> DataFrame:
    """(bucket, part, n): what each part has put into each bucket. Parts write apart, so no two contend for a slice."""
    rows = stage.spark.read.option("basePath", stage.folder).parquet(*stage.committed())
    return rows.groupBy("bucket", F.col("part").cast("int").alias("part")).agg(F.count(F.lit(1)).alias("n"))


def tree_stage(run: Run, summaries: DataFrame, cfg: IndexConfig, mode: str = "leaf", fault: Fault | None = None, parts: int | None = None, **options) -> DataFrame:
    """(bucket, path, n_items) of the forest under one of the modes, which differ in how helpers take part.

    leaf: parts are pieces of buckets; an owner builds its part as a whole, a helper by groups of pieces, and only
    those not there yet. subtree: parts are whole buckets, owner and helper alike build them as a whole. standard: no part is
    ever fast; all are written by groups of pieces from the start. private: as leaf, but helpers too build a whole
    part of their own, and one of the copies is published.
    """
    parts = parts or cfg.k_chunks
    spark, m = summaries.sparkSession, cfg.m_groups
    keyed = stored(heads(summaries, cfg))
    key = ["bucket"] if mode == "subtree" else ["bucket", "head"]
    of = F.pmod(F.xxhash64(*key), F.lit(parts * m)).cast("int")

    def make(part: int, group: int | None = None) -> DataFrame:
        return pieces(keyed.where(F.floor(of / m) == part if group is None else of == part * m + group), cfg)

    options.setdefault("backoff_factor", cfg.backoff_factor)
    if mode == "standard":
        deep = staged(run, "tree", spark, parts * m, lambda p: make(p // m, p % m), fault, **options)
    else:
        deep = staged(run, "tree", spark, parts, make, fault, m if mode == "leaf" else 1, **options)
    return assemble(deep, cfg)


def prune_stage(run: Run, index: SeriesIndex, q: Q.Queries, bsf: np.ndarray, fault: Fault | None = None, **options) -> DataFrame:
    """(query_id, series_id, leaf_id, lb, queue_id): candidates, from parts that are runs of leaves."""
    cfg = index.cfg
    k = cfg.k_chunks

    def make(part: int) -> DataFrame:
        mine = replace(index, nodes=index.nodes.where(part_of("leaf_id", k) == part), by_leaf=index.by_leaf.where(part_of("leaf_id", k) == part))
        return Q.deal(Q._item_bounds(mine, q, bsf, Q.asked_leaves(Q.leaf_bounds(mine.leaves, q, bsf, cfg), True)), index)

    return staged(run, "prune", index.nodes.sparkSession, k, make, fault, backoff_factor=cfg.backoff_factor, **options)


def refine_stage(run: Run, index: SeriesIndex, q: Q.Queries, bsf: np.ndarray, queued: DataFrame, k: int, fault: Fault | None = None, **options) -> DataFrame:
    """(query_id, series_id, dist): each queue is a part of its own, and sets of queries are its groups for helpers."""
    cfg = index.cfg
    queued, m = small(cut(queued)), cfg.m_groups if cfg.levels > 1 else 1

    def make(part: int, group: int | None = None) -> DataFrame:
        mine = queued.where(F.col("queue_id") == part)
        # a leaf's candidates are in one queue, so a queue looks only at the values of its own leaves
        own = replace(index, by_leaf=Q.enqueue(index.by_leaf, cfg.queues).where(F.col("queue_id") == part).drop("queue_id")) if index.raw is None else index
        return Q.refine(mine if group is None else mine.where(part_of("query_id", m) == group), own, q, bsf, k)

    return staged(run, "refine", queued.sparkSession, cfg.queues, make, fault, m, backoff_factor=cfg.backoff_factor, **options)


def build(series: DataFrame, cfg: IndexConfig, mode: str = "leaf", faults: dict[str, Fault] | None = None, **options) -> Run:
    run, faults = Run(), faults or {}
    full = summaries_stage(run, series, cfg, faults.get("summarize"), **options)
    summaries = full.select("series_id", "paa", "word", "bucket")
    raw = tree_stage(run, summaries, cfg, mode, faults.get("tree"), **options)
    nodes, at = X.populate(summaries, cfg, X.node_shapes(raw, cfg))
    run.index = SeriesIndex(cfg, summaries, nodes, stored(X.cluster_by_leaf(full.select("series_id", "word", "values"), at)))
    return run


def ask(run: Run, queries: DataFrame, k: int = 1, faults: dict[str, Fault] | None = None, **options) -> Run:
    """Prunes and refines against a built index; (query_id, series_id, dist, rank) in ``run.answers``."""
    index, faults = run.index, faults or {}
    q = Q.Queries.of(queries, index.cfg)
    best = cut(Q.top_k(Q.seed(index, q, index.cfg.seed_how, k), k))
    bsf = Q._kth(best, q, k)
    queued = prune_stage(run, index, q, bsf, faults.get("prune"), **options)
    got = refine_stage(run, index, q, bsf, queued, k, faults.get("refine"), **options)
    run.answers = cut(Q.top_k(best.select("query_id", "series_id", "dist").unionByName(got), k))
    return run


def answer(series: DataFrame, queries: DataFrame, cfg: IndexConfig, k: int = 1, mode: str = "leaf", faults: dict[str, Fault] | None = None, **options) -> Run:
    """The exact k nearest of each query by the four stages; ``faults`` names a stage each."""
    return ask(build(series, cfg, mode, faults, **options), queries, k, faults, **options)


def delete_min(queued: DataFrame, index: SeriesIndex, q: Q.Queries, bsf: np.ndarray, k: int = 1) -> DataFrame:
    """(query_id, series_id, dist) from one shared queue in order of bound: the least is taken out again and again, by one
    consumer, until bounds pass all that can still improve."""
    cfg, n, slack, valued = index.cfg, index.cfg.n, index.cfg.slack, index.raw is None
    shared = queued.sparkSession.sparkContext.broadcast((q.ids, q.values, bsf))
    rows = Q.with_values(queued, index).select("query_id", "series_id", "lb", "values").repartition(1).sortWithinPartitions("lb", "query_id", "series_id")

    def run(batches):
        ids, values, bsf = shared.value
        limit, best = bsf.copy(), [np.zeros(0) for _ in ids]
        for b in batches:
            lb = b.column(2).to_numpy()
            if not b.num_rows or lb[0] * (1 - slack) > limit.max(initial=-np.inf):
                return
            which = np.searchsorted(ids, b.column(0).to_numpy())
            at = np.flatnonzero(lb * (1 - slack) <= limit[which])
            x = matrix(b.column(3), n)[at]
            x = x if valued else X.normal(x, cfg)
            d = S.distances(x, values[which[at]], limit[which[at]])
            got = at[np.isfinite(d)]
            d = d[np.isfinite(d)]
            for j, y in zip(which[got].tolist(), d.tolist(), strict=True):
                best[j] = np.sort(np.append(best[j], y))[:k]
                if len(best[j]) == k:
                    limit[j] = min(limit[j], best[j][-1])
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(got)), b.column(1).take(pa.array(got)), pa.array(d)], names=["query_id", "series_id", "dist"])

    return rows.mapInArrow(run, Q.ANSWER)


def single_queue(run: Run, queries: DataFrame, k: int = 1, fault: Fault | None = None, **options) -> Run:
    """The baseline of pruning and refinement: nodes are taken one after the other by a counter and looked at again,
    all candidates go into one queue, and that is emptied by delete-min."""
    index = replace(run.index, cfg=replace(run.index.cfg, queues=1))
    q = Q.Queries.of(queries, index.cfg)
    best = cut(Q.top_k(Q.seed(index, q, index.cfg.seed_how, k), k))
    bsf = Q._kth(best, q, k)
    run.index, built = index, run.index
    queued = prune_stage(run, index, q, bsf, fault, claim="counter", **options)
    run.index = built
    got = delete_min(small(queued), index, q, bsf, k)
    run.answers = cut(Q.top_k(best.select("query_id", "series_id", "dist").unionByName(got), k))
    return run
