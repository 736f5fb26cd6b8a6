"""The competitors: the same four stages under other ways to share the work. All give the same answers.

barrier and leaf_lock are Spark's own tasks and stage barrier over whole buckets or pieces of them. static_split,
counter_claim and cas_claim share one buffer, as large as the collection, by done flags, a counter or claims; their trees
take series one by one, with or without a flag at the parent for each insert; one queue serves their queries.
direct_insert has no buffer at all. What an atomic instruction costs has no counterpart here; how many claims, looks
and losses there are is counted.
"""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import IndexConfig
from ..session import cut, stored
from . import index as X
from . import staged as G
from .index import SeriesIndex, subtree
from .parts import Fault, Stage, run_parts
from .series import Raw

STRATEGIES = ("helping", "barrier", "leaf_lock", "static_split", "counter_claim", "cas_claim", "direct_insert", "platform")
MODES = ("leaf", "subtree", "standard", "private")
CLAIMS = {"static_split": "circle", "counter_claim": "counter", "cas_claim": "cas"}
TREE = "bucket int, path string, n_items bigint"


def subtrees_by_bucket(summaries: DataFrame, cfg: IndexConfig) -> DataFrame:
    """One task a bucket: a heavy bucket is one heavy task, which is this baseline's weak point."""

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        nodes = subtree(np.stack(pdf.word.to_numpy()), np.ones(len(pdf), dtype=np.int64), cfg)
        return pd.DataFrame({"bucket": int(pdf.bucket.iloc[0]), "path": [p for p, _ in nodes], "n_items": [n for _, n in nodes]})

    return summaries.select("bucket", "word").groupBy("bucket").applyInPandas(build, TREE)


def subtrees_by_pieces(summaries: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Several tasks a bucket: each builds the tree below one prefix of a few bits; the nodes above come from counts."""
    return G.assemble(cut(G.pieces(G.heads(summaries, cfg), cfg)), cfg)


def inserted(words: np.ndarray, cfg: IndexConfig, flagged: bool = False) -> tuple[dict[str, int], dict[str, int]]:
    """(items of each node, counts of work) of one bucket's tree that takes its words one by one. ``flagged``: each insert
    raises and lowers a flag at the leaf's parent, so that a split and an insert don't meet; else only splits are marked."""
    items, held, done = {"": 0}, {"": []}, {"inserts": 0, "splits": 0, "flags": 0}
    for k in range(len(words)):
        path = ""
        while True:
            items[path] += 1
            if path in held:
                break
            d = len(path)
            path += str((words[k, d % cfg.w] >> (cfg.bits - 2 - d // cfg.w)) & 1)
        held[path].append(k)
        done["inserts"] += 1
        done["flags"] += 2 * flagged
        work = [path]
        while work:
            path = work.pop()
            d = len(path)
            if len(held[path]) > cfg.theta and d < cfg.max_depth:
                done["splits"] += 1
                done["flags"] += 1
                mine = held.pop(path)
                bit = (words[mine, d % cfg.w] >> (cfg.bits - 2 - d // cfg.w)) & 1
                for side in (0, 1):
                    child = path + str(side)
                    held[child] = [m for m, b in zip(mine, bit, strict=True) if b == side]
                    items[child] = len(held[child])
                    work.append(child)
    return items, done


def trees_one_by_one(summaries: DataFrame, cfg: IndexConfig, flagged: bool = False) -> DataFrame:
    """(bucket, path, n_items, inserts, splits, flags): element-wise inserts; the counts stand at each tree's root."""

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        items, done = inserted(np.stack(pdf.word.to_numpy()), cfg, flagged)
        out = pd.DataFrame({"bucket": int(pdf.bucket.iloc[0]), "path": list(items), "n_items": list(items.values())})
        for name, n in done.items():
            out[name] = np.where(out.path == "", n, 0)
        return out

    return summaries.select("bucket", "word").groupBy("bucket").applyInPandas(build, TREE + ", inserts bigint, splits bigint, flags bigint")


def summarize(series: DataFrame, cfg: IndexConfig, strategy: str, workers: int = 4, fault: Fault | None = None, run: G.Run | None = None, keep_values: bool = True) -> DataFrame:
    """Summaries, with values unless told otherwise, under a way to share the collection.

    helping: chunks with a ledger and helpers, each laid out by bucket. static_split, counter_claim, cas_claim: parts of one
    buffer in the collection's order, shared as :func:`run_parts` says; static_split has a part a worker, the others
    many. barrier, leaf_lock: Spark's tasks and barrier. platform: the same, with what Spark itself does for late and failed
    tasks. direct_insert: nothing is kept for the tree.
    """
    run = run if run is not None else G.Run()
    if strategy == "helping":
        return G.summaries_stage(run, series, cfg, fault, keep_values, owners=workers)
    if strategy in CLAIMS:
        n = workers if strategy == "static_split" else 4 * cfg.k_chunks // 2
        stage = run.stages["summarize"] = Stage(series.sparkSession, "buffer")
        run.ledgers["summarize"] = run_parts(stage, range(n), lambda p: X.summarize(series.where(G.part_of("series_id", n) == p), cfg, keep_values), owners=workers, fault=fault, claim=CLAIMS[strategy])
        return stage.read().select("series_id", "paa", "word", "bucket", *["values"] * keep_values)
    full = X.summarize(series, cfg, keep_values)
    return full if strategy == "direct_insert" else cut(full) if keep_values else stored(full)


def tree(summaries: DataFrame, cfg: IndexConfig, strategy: str, flagged: bool = False, fault: Fault | None = None, run: G.Run | None = None, workers: int = 4) -> DataFrame | None:
    """Node counts by the strategy, or None where the level-wise builder does it."""
    if strategy == "helping":
        return G.tree_stage(run if run is not None else G.Run(), summaries, cfg, cfg.mode, fault, owners=workers)
    if strategy == "barrier":
        return subtrees_by_bucket(summaries, cfg)
    if strategy == "leaf_lock":
        return subtrees_by_pieces(summaries, cfg)
    if strategy in CLAIMS or strategy == "direct_insert":
        return trees_one_by_one(summaries, cfg, flagged).select("bucket", "path", "n_items")
    return None


def tree_by_parts(summaries: DataFrame, cfg: IndexConfig, mode: str, fault: Fault | None = None, parts: int = 4) -> tuple[DataFrame, DataFrame]:
    """(node counts, ledger): the tree built in ledgered parts under one of the four modes."""
    run = G.Run()
    raw = G.tree_stage(run, summaries, cfg, mode, fault, parts)
    return raw, run.ledgers["tree"]


def build(series: DataFrame, cfg: IndexConfig, strategy: str | None = None, mode: str | None = None, workers: int = 4, fault: Fault | None = None, flagged: bool = False, raw: Raw | None = None) -> SeriesIndex:
    """An index of any strategy or tree mode; equal trees and equal answers for all of them. With ``raw`` the values stay there."""
    strategy = strategy or cfg.strategy
    if cfg.split_policy != "round_robin":
        return X.build(series, cfg, raw)
    full = summarize(series, cfg, strategy, workers, fault if mode is None else None, keep_values=raw is None)
    summaries = full.select("series_id", "paa", "word", "bucket")
    counts = tree_by_parts(summaries, cfg, mode, fault)[0] if mode else tree(summaries, cfg, strategy, flagged, workers=workers)
    nodes, assignments = X.populate(summaries, cfg, None if counts is None else X.node_shapes(counts, cfg))
    queues = 1 if strategy in (*CLAIMS, "direct_insert") else cfg.queues
    return SeriesIndex(replace(cfg, queues=queues), summaries, nodes, stored(X.cluster_by_leaf(full.select(*X.VALUED[: 3 if raw is None else 2]), assignments)), raw)
