"""Buckets and the forest: from series to summaries, from summaries to a leaf-oriented tree in each bucket.

The tree is built set at a time over distinct words with counts, so a hot bucket or word is one row
however many series share it. Under the round-robin policy the path of a word doesn't depend on the
data, and several levels are counted by one aggregation.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import IndexConfig
from ..functions import summaries as S
from ..session import apart, cut, small, stored
from .series import Raw, lists, matrix

STRIDE = 8
FEW_WORDS = 50_000
#: Distinct words of a balanced tree, and items when words find their leaves, that one task takes as a whole.
PIECE = 20_000
#: Leaves that are kept together when values are dealt out.
RUN = 64
SUMMARY = "series_id bigint, paa array<double>, word array<int>, bucket int"


def summarize(series: DataFrame, cfg: IndexConfig, keep_values: bool = False) -> DataFrame:
    """(series_id, paa, word, bucket[, values normalised]): a narrow projection, no shuffle."""

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            x = matrix(b.column(1), cfg.n)
            x = normal(x, cfg)
            paa = S.paa_rows(x, cfg.w)
            word = S.symbol_rows(paa, cfg.bits)
            cols = [b.column(0), lists(paa), lists(word, pa.int32()), pa.array(S.bucket_rows(word, cfg.bits).astype(np.int32))]
            yield pa.RecordBatch.from_arrays(cols + [lists(x)] * keep_values, names=["series_id", "paa", "word", "bucket"] + ["values"] * keep_values)

    return series.select("series_id", "values").mapInArrow(run, SUMMARY + ", values array<double>" * keep_values)


def bucket_stats(summaries: DataFrame) -> DataFrame:
    return summaries.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


def path_bits(word, cfg: IndexConfig):
    """All bits below the first of a word in round-robin order, as a string: the path to its deepest node."""
    bits = [F.shiftright(F.get(word, F.lit(d % cfg.w)), cfg.bits - 2 - d // cfg.w).bitwiseAND(1).cast("string") for d in range(cfg.max_depth)]
    return F.concat(*bits)


def subtree(words: np.ndarray, counts: np.ndarray, cfg: IndexConfig, path: str = "", depth: int = 0) -> list[tuple[str, int]]:
    """(path, items) of all nodes of one bucket's round-robin tree, built by one worker."""
    out, work = [], [(path, depth, np.arange(len(words)))]
    while work:
        path, d, rows = work.pop()
        n = int(counts[rows].sum())
        out.append((path, n))
        if n > cfg.theta and d < cfg.max_depth:
            bit = (words[rows, d % cfg.w] >> (cfg.bits - 2 - d // cfg.w)) & 1
            work += [(path + "1", d + 1, rows[bit == 1]), (path + "0", d + 1, rows[bit == 0])]
    return out


def _round_robin_few(words: DataFrame, cfg: IndexConfig) -> DataFrame:
    """The trees of at most FEW_WORDS distinct words, one task a bucket."""

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        nodes = subtree(np.stack(pdf.word.to_numpy()), pdf.n.to_numpy(), cfg)
        return pd.DataFrame({"bucket": int(pdf.bucket.iloc[0]), "path": [p for p, _ in nodes], "n_items": [n for _, n in nodes]})

    return node_shapes(words.groupBy("bucket").applyInPandas(build, "bucket int, path string, n_items bigint"), cfg)


def node_shapes(counts: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Adds the split segment and the bits of each segment, which round-robin depth gives."""
    depth = F.length("path")
    seg = F.when((F.col("n_items") > cfg.theta) & (depth < cfg.max_depth), depth % cfg.w).cast("int")
    used = F.transform(F.sequence(F.lit(0), F.lit(cfg.w - 1)), lambda j: (1 + F.floor((depth + cfg.w - 1 - j) / cfg.w)).cast("int"))
    return counts.select("bucket", "path", "n_items", seg.alias("seg_split"), used.alias("bits"))


def _round_robin(words: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(bucket, path, n_items, splits) of all nodes, level by level; a checked small number of words is built at once."""
    if words.limit(FEW_WORDS + 1).count() <= FEW_WORDS:
        return _round_robin_few(words, cfg)
    paths = stored(words.select("bucket", "word", path_bits(F.col("word"), cfg).alias("bits"), "n"))
    roots = paths.groupBy("bucket").agg(F.sum("n").alias("n_items"), F.count(F.lit(1)).alias("words")).select("bucket", F.lit("").alias("path"), "n_items", "words")
    parts, alive, depth = [], stored(roots), 0
    while True:
        # what lies below a node of few words is built at once
        few = alive.where((F.col("n_items") <= cfg.theta) | (F.col("words") <= PIECE) | (F.lit(depth) >= cfg.max_depth)).select("bucket", "path", "n_items", "words")
        parts.append(few.where("words = 0").select("bucket", "path", "n_items"))
        mine = paths.withColumn("path", F.substring("bits", 1, depth)).join(small(few.select("bucket", "path")), ["bucket", "path"], "left_semi")
        parts.append(stored(split_leaves(mine.select("bucket", "path", "word", "n"), cfg)))
        big = alive.join(few.select("bucket", "path"), ["bucket", "path"], "left_anti")
        if big.isEmpty():
            break
        split, top = big.select("bucket", "path"), min(depth + STRIDE, cfg.max_depth)
        parts.append(big.select("bucket", "path", "n_items"))
        under = paths.withColumn("path", F.substring("bits", 1, depth)).join(small(split), ["bucket", "path"], "left_semi").select("bucket", "bits", "n")
        counted = under.select("bucket", F.explode(F.transform(F.sequence(F.lit(depth + 1), F.lit(top)), lambda d: F.substring("bits", F.lit(1), d))).alias("path"), "n").groupBy("bucket", "path").agg(F.sum("n").alias("n_items"), F.count(F.lit(1)).alias("words"))
        counted = cut(counted)
        # a node is there if its parent splits; the sibling without items is an empty leaf
        for d in range(depth + 1, top + 1):
            both = split.select("bucket", F.explode(F.array(F.concat("path", F.lit("0")), F.concat("path", F.lit("1")))).alias("path"))
            level = both.join(apart(counted.where(F.length("path") == d)), ["bucket", "path"], "left").select("bucket", "path", F.coalesce("n_items", F.lit(0)).alias("n_items"), F.coalesce("words", F.lit(0)).alias("words"))
            alive = level
            if d < top:
                level = cut(level)
                parts.append(level.select("bucket", "path", "n_items"))
                split = level.where(F.col("n_items") > cfg.theta).select("bucket", "path")
        alive, depth = cut(alive), top
    nodes = parts[0]
    for p in parts[1:]:
        nodes = nodes.unionByName(p)
    return node_shapes(nodes, cfg)


def _seg_bit(word, bits, seg, cfg: IndexConfig):
    """The next bit of a segment below its ``bits`` used ones."""
    return F.call_function("shiftright", F.get(word, seg), F.lit(cfg.bits - 1) - F.get(bits, seg)).bitwiseAND(1)


def balanced_subtree(words: np.ndarray, counts: np.ndarray, cfg: IndexConfig, path: str, bits: np.ndarray) -> list[tuple[str, int, int | None, np.ndarray]]:
    """(path, items, split segment or None, bits) of all nodes from ``path`` down, each split on the segment whose next bit
    parts its items most evenly (least segment on ties). Children without items are there as empty leaves."""
    out, work = [], [(path, np.asarray(bits), np.arange(len(words)))]
    while work:
        path, bits, rows = work.pop()
        n, open_ = int(counts[rows].sum()), np.flatnonzero(bits < cfg.bits)
        if n <= cfg.theta or not len(open_):
            out.append((path, n, None, bits))
            continue
        ones = (words[rows][:, open_] >> (cfg.bits - 1 - bits[open_])) & 1
        best = int(np.argmin(np.abs(2 * (counts[rows, None] * ones).sum(axis=0) - n)))
        out.append((path, n, int(open_[best]), bits))
        below = bits.copy()
        below[open_[best]] += 1
        work += [(path + str(side), below, rows[ones[:, best] == side]) for side in (1, 0)]
    return out


def _balanced(words: DataFrame, cfg: IndexConfig) -> DataFrame:
    """As above, each node split on the segment whose next bit parts its items most evenly (least segment on ties). Nodes of
    more than PIECE distinct words are split level by level; the tree below any other is built in one task."""
    state = cut(words.select("bucket", "word", "n", F.lit("").alias("path"), F.array_repeat(F.lit(1), cfg.w).alias("bits")))
    parts = []

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        nodes = balanced_subtree(np.stack(pdf.word.to_numpy()), pdf.n.to_numpy(), cfg, pdf.path.iloc[0], pdf.bits.iloc[0])
        bucket = int(pdf.bucket.iloc[0])
        return pd.DataFrame([(bucket, p, n, seg, bits) for p, n, seg, bits in nodes], columns=["bucket", "path", "n_items", "seg_split", "bits"]).astype({"seg_split": "Int32"})

    schema = "bucket int, path string, n_items bigint, seg_split int, bits array<int>"
    while True:
        ones = [F.sum(F.when(F.get("bits", F.lit(j)) < cfg.bits, F.col("n") * _seg_bit("word", "bits", F.lit(j), cfg))).alias(f"o{j}") for j in range(cfg.w)]
        level = state.groupBy("bucket", "path", "bits").agg(F.sum("n").alias("n_items"), F.count(F.lit(1)).alias("words"), *ones)
        off = [F.struct(F.abs(2 * F.col(f"o{j}") - F.col("n_items")).alias("off"), F.lit(j).alias("seg")) for j in range(cfg.w)]
        best = F.array_min(F.filter(F.array(*off), lambda x: x["off"].isNotNull()))
        big = cut(level.where(F.col("words") > PIECE).select("bucket", "path", "n_items", F.when(F.col("n_items") > cfg.theta, best["seg"]).cast("int").alias("seg_split"), "bits"))
        rest = state.join(small(big.select("bucket", "path")), ["bucket", "path"], "left_anti")
        parts.append(cut(rest.groupBy("bucket", "path").applyInPandas(build, schema)))
        split = big.where("seg_split is not null").select("bucket", "path", "seg_split")
        if split.isEmpty():
            parts.append(big)
            break
        # both children of a node that is split level by level hold words, or its empty one is a leaf
        sides = split.join(big.select("bucket", "path", "bits"), ["bucket", "path"]).select("bucket", F.explode(F.array(F.concat("path", F.lit("0")), F.concat("path", F.lit("1")))).alias("path"), F.transform("bits", lambda b, j: F.when(j == F.col("seg_split"), b + 1).otherwise(b)).alias("bits"))
        bit = _seg_bit("word", "bits", F.col("seg_split"), cfg)
        state = cut(state.join(small(split), ["bucket", "path"]).select("bucket", "word", "n", F.concat("path", bit.cast("string")).alias("path"), F.transform("bits", lambda b, j: F.when(j == F.col("seg_split"), b + 1).otherwise(b)).alias("bits")))
        empty = sides.join(state.select("bucket", "path").distinct(), ["bucket", "path"], "left_anti").select("bucket", "path", F.lit(0).cast("bigint").alias("n_items"), F.lit(None).cast("int").alias("seg_split"), "bits")
        parts += [big, cut(empty)]
    nodes = parts[0]
    for p in parts[1:]:
        nodes = nodes.unionByName(p)
    return nodes


def in_order_key(path="path"):
    """A key whose order is the in-order of the tree: left subtree, node, right subtree."""
    return F.concat(F.translate(path, "01", "az"), F.lit("m"))


def populate(summaries: DataFrame, cfg: IndexConfig, raw: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(nodes, assignments): the whole forest, and the leaf of every series. ``raw``: a node table built elsewhere."""
    words = summaries.groupBy("bucket", "word").agg(F.count(F.lit(1)).alias("n"))
    if raw is None:
        raw = _round_robin(words, cfg) if cfg.split_policy == "round_robin" else _balanced(words, cfg)
    nodes = forest(raw, cfg)
    return nodes, assign(words.select("bucket", "word"), summaries, nodes, cfg)


def forest(raw: DataFrame, cfg: IndexConfig) -> DataFrame:
    """The node table with depth, left counts, in-order places, dense leaf ids, symbols and ranges."""
    raw = raw.withColumns({"depth": F.length("path"), "is_leaf": F.col("seg_split").isNull()})
    ranked = stored(_ranked(raw, cfg))
    # leaf ids are dense over the forest: offsets of the at most 2**w buckets
    totals = ranked.groupBy("bucket").agg(F.sum(F.col("is_leaf").cast("bigint")).alias("t"))
    offsets = totals.withColumn("_at", F.coalesce(F.sum("t").over(Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("t")
    nodes = ranked.join(F.broadcast(offsets), "bucket").withColumn("leaf_id", F.when(F.col("is_leaf"), F.col("_at") + F.col("_leaf") - 1))
    return stored(_with_ranges(nodes.select("bucket", "path", "depth", "is_leaf", "n_items", "seg_split", "bits", "left_nodes", "inorder", "leaf_id"), cfg))


def _ranked(raw: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Adds left_nodes, inorder and _leaf, the number of leaves so far, by one pass over each bucket in order. Of a node's left
    subtree all nodes are deeper than it, and the node before them, if any, is an ancestor."""

    def run(batches):
        at, held, place, leaves = None, [], 0, 0
        for b in batches:
            left, inorder, leaf = (np.zeros(b.num_rows, dtype=np.int64) for _ in range(3))
            for k, (bucket, depth, is_leaf) in enumerate(zip(b.column(0).to_pylist(), b.column(5).to_pylist(), b.column(6).to_pylist(), strict=True)):
                if bucket != at:
                    at, held, place, leaves = bucket, [], 0, 0  # held: (depth, place) of the nodes with none of less depth after them
                place += 1
                leaves += is_leaf
                while held and held[-1][0] > depth:
                    held.pop()
                left[k], inorder[k], leaf[k] = place - 1 - (held[-1][1] if held else 0), place, leaves
                held.append((depth, place))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(left), pa.array(inorder), pa.array(leaf)], names=[*b.schema.names, "left_nodes", "inorder", "_leaf"])

    rows = raw.select("bucket", "path", "n_items", "seg_split", "bits", "depth", "is_leaf").repartition("bucket").sortWithinPartitions("bucket", in_order_key())
    return rows.mapInArrow(run, "bucket int, path string, n_items bigint, seg_split int, bits array<int>, depth int, is_leaf boolean, left_nodes bigint, inorder bigint, _leaf bigint")


def _with_ranges(nodes: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Adds syms, lo and hi by replaying each path from its bucket."""

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            syms = (b.column(0).to_numpy()[:, None] >> (cfg.w - 1 - np.arange(cfg.w))).astype(np.int64) & 1
            used = matrix(b.column(6), cfg.w).astype(np.int64)
            depth, at = b.column(2).to_numpy(), np.arange(b.num_rows)
            text = np.array(b.column(1).to_pylist(), dtype=bytes)
            path = text.view(np.uint8).reshape(len(text), -1) - ord("0")
            segs, starts = b.column(10).flatten().to_numpy(zero_copy_only=False), np.cumsum(depth) - depth
            for d in range(int(depth.max())):
                live = at[depth > d]
                j = segs[starts[live] + d].astype(np.int64) if len(segs) else d % cfg.w
                syms[live, j] = syms[live, j] << 1 | path[live, d]
            lo, hi = S.intervals(syms, used, cfg.bits)
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in range(10)), lists(syms.astype(np.int32), pa.int32()), lists(lo), lists(hi)], names=[*names, "syms", "lo", "hi"])

    names = nodes.columns
    if cfg.split_policy == "round_robin":
        nodes = nodes.withColumn("segs", F.lit(None).cast("array<int>"))
    else:  # the segments that a node's ancestors split on, top down
        ups = nodes.where("depth > 0").select("bucket", "path", F.explode(F.transform(F.sequence(F.lit(0), F.col("depth") - 1), lambda d: F.substring("path", F.lit(1), d))).alias("up"))
        of = nodes.select("bucket", F.col("path").alias("up"), F.col("seg_split").alias("s"))
        segs = apart(ups).join(of, ["bucket", "up"]).groupBy("bucket", "path").agg(F.sort_array(F.collect_list(F.struct(F.length("up").alias("d"), "s"))).alias("x")).select("bucket", "path", F.transform("x", lambda x: x["s"]).alias("segs"))
        nodes = nodes.join(segs, ["bucket", "path"], "left")
    schema = "bucket int, path string, depth int, is_leaf boolean, n_items bigint, seg_split int, bits array<int>, left_nodes bigint, inorder bigint, leaf_id bigint, syms array<int>, lo array<double>, hi array<double>"
    return nodes.select(*names, "segs").mapInArrow(run, schema)


def _descend(words: DataFrame, nodes: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(word, leaf_id) by the splits of the nodes: through the few nodes of more than PIECE items first, then one task goes on
    for all words and nodes below the same one."""
    tops = {(r[0], r[1]): r[2] for r in nodes.where((F.col("n_items") > PIECE) & F.col("seg_split").isNotNull()).select("bucket", "path", "seg_split").collect()}  # a depth's share is at most items / PIECE
    shared = nodes.sparkSession.sparkContext.broadcast(tops)

    def heads(batches):
        for b in batches:
            out = []
            for bucket, word in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                path, used = "", [1] * cfg.w
                while (seg := shared.value.get((bucket, path))) is not None:
                    path += str((word[seg] >> (cfg.bits - 1 - used[seg])) & 1)
                    used[seg] += 1
                out.append(path)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(out, pa.string())], names=["bucket", "word", "head"])

    def above(batches):
        for b in batches:
            out = []
            for bucket, path in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                d = 0
                while d < len(path) and (bucket, path[:d]) in shared.value:
                    d += 1
                out.append(path[:d])
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out, pa.string())], names=[*b.schema.names, "head"])

    def find(words: pd.DataFrame, nodes: pd.DataFrame) -> pd.DataFrame:
        out = np.full(len(words), -1, dtype=np.int64)
        if len(words) and len(nodes):
            x = np.stack(words.word.to_numpy()).astype(np.int64)
            tree = {r.path: (r.seg_split, r.leaf_id, r.bits) for r in nodes.itertuples()}
            work = [(words["head"].iloc[0], np.arange(len(x)))]
            while work:
                path, rows = work.pop()
                if path not in tree or not len(rows):
                    continue
                seg, leaf, bits = tree[path]
                if pd.isna(seg):
                    out[rows] = int(leaf)
                    continue
                bit = (x[rows, int(seg)] >> (cfg.bits - 1 - int(bits[int(seg)]))) & 1
                work += [(path + str(side), rows[bit == side]) for side in (0, 1)]
        return pd.DataFrame({"word": words.word[out >= 0], "leaf_id": out[out >= 0]})

    probes = words.select("bucket", "word").mapInArrow(heads, "bucket int, word array<int>, head string")
    under = nodes.select("bucket", "path", "seg_split", "leaf_id", "bits").mapInArrow(above, "bucket int, path string, seg_split int, leaf_id bigint, bits array<int>, head string")
    return probes.groupBy("bucket", "head").cogroup(under.groupBy("bucket", "head")).applyInPandas(find, "word array<int>, leaf_id bigint")


def assign(words: DataFrame, summaries: DataFrame, nodes: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(series_id, leaf_id, word): each distinct word finds its leaf once, then series join on the word. Few words try each
    depth at which there are leaves; more go down the trees."""
    leaves = nodes.where("is_leaf")
    if cfg.split_policy == "round_robin" and words.limit(FEW_WORDS + 1).count() <= FEW_WORDS:
        depths = [r[0] for r in leaves.select("depth").distinct().orderBy("depth").collect()]  # at most max_depth + 1 rows
        if not depths:
            return summaries.select("series_id", F.lit(None).cast("bigint").alias("leaf_id"), "word").limit(0)
        bits = words.select("bucket", "word", path_bits(F.col("word"), cfg).alias("_bits"))
        probes = bits.select("bucket", "word", F.explode(F.array(*(F.substring("_bits", 1, d) for d in depths))).alias("path"))
        found = apart(probes).join(leaves.select("bucket", "path", "leaf_id"), ["bucket", "path"]).select("word", "leaf_id")
    else:
        found = _descend(words, nodes, cfg)
    return apart(summaries.select("series_id", "word")).join(found, "word").select("series_id", "leaf_id", "word")


def node_at(nodes: DataFrame, bucket: int, i: int) -> DataFrame:
    """The i-th node of a bucket's tree in in-order, from 1."""
    return nodes.where((F.col("bucket") == bucket) & (F.col("inorder") == i))


def tree_size(nodes: DataFrame) -> DataFrame:
    """(bucket, total): nodes of each tree, from the left counts along its rightmost path."""
    return nodes.where(F.col("path").rlike("^1*$")).groupBy("bucket").agg(F.sum(F.col("left_nodes") + 1).alias("total"))


def tree_equal(a: DataFrame, b: DataFrame) -> bool:
    cols = ["bucket", "path", "n_items"]
    return a.select(cols).exceptAll(b.select(cols)).isEmpty() and b.select(cols).exceptAll(a.select(cols)).isEmpty()


def tree_stats(nodes: DataFrame) -> DataFrame:
    leaf = F.col("is_leaf")
    return nodes.agg(F.countDistinct("bucket").alias("roots"), F.count(F.lit(1)).alias("nodes"), F.sum(leaf.cast("bigint")).alias("leaves"), F.sum((leaf & (F.col("n_items") == 0)).cast("bigint")).alias("empty_leaves"), F.max("depth").alias("max_depth"), F.coalesce(F.sum(F.when(leaf, F.col("n_items"))), F.lit(0)).alias("items"))


@dataclass
class SeriesIndex:
    cfg: IndexConfig
    summaries: DataFrame  # series_id, paa, word, bucket
    nodes: DataFrame
    by_leaf: DataFrame  # leaf_id, series_id, word[, values (normalised)], clustered by leaf
    raw: Raw | None = None  # where by_leaf has no values: the collection they are taken from

    @cached_property
    def leaves(self) -> DataFrame:
        return self.nodes.where("is_leaf and n_items > 0").select("leaf_id", "bucket", "n_items", "lo", "hi")

    def stats(self) -> DataFrame:
        return tree_stats(self.nodes)

    @property
    def values(self) -> DataFrame:
        """(series_id, values), normalised where by_leaf has them."""
        return self.by_leaf.select("series_id", "values") if self.raw is None else self.raw.frame


def normal(x: np.ndarray, cfg: IndexConfig) -> np.ndarray:
    return S.znorm_rows(x) if cfg.normalise == "z" else x


def cluster_by_leaf(full: DataFrame, assignments: DataFrame) -> DataFrame:
    """The members, with their values where ``full`` has them, dealt out by runs of leaves and sorted by word inside, so that a
    leaf is a run of rows. Leaf ids are dense, so no sample is taken for ranges, which would join the values twice."""
    joined = assignments.select("leaf_id", "series_id", "word")
    if "values" in full.columns:
        joined = apart(full).join(joined.drop("word"), "series_id").select("leaf_id", "series_id", "word", "values")
    return joined.repartition(F.floor(F.col("leaf_id") / RUN)).sortWithinPartitions("leaf_id", "word", "series_id")


VALUED = ["series_id", "word", "values"]


def build(series: DataFrame, cfg: IndexConfig, raw: Raw | None = None) -> SeriesIndex:
    """Summaries, forest and clustered values of a collection; with ``raw`` the values stay there."""
    full = cut(summarize(series, cfg, keep_values=True)) if raw is None else stored(summarize(series, cfg))
    summaries = full.select("series_id", "paa", "word", "bucket")
    nodes, assignments = populate(summaries, cfg)
    return SeriesIndex(cfg, summaries, nodes, stored(cluster_by_leaf(full.select(*VALUED[: 3 if raw is None else 2]), assignments)), raw)


def overflow_leaves(nodes: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Leaves over their capacity whose words can't be told apart."""
    return nodes.where(F.col("is_leaf") & (F.col("n_items") > cfg.theta))


def split_leaves(words: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(bucket, path, n_items) of the trees that overfull leaves become, the leaf itself included; words: bucket, path, word, n."""

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        top = pdf.path.iloc[0]
        nodes = subtree(np.stack(pdf.word.to_numpy()), pdf.n.to_numpy(), cfg, top, len(top))
        return pd.DataFrame({"bucket": int(pdf.bucket.iloc[0]), "path": [p for p, _ in nodes], "n_items": [n for _, n in nodes]})

    return words.groupBy("bucket", "path").applyInPandas(build, "bucket int, path string, n_items bigint")


def insert_batch(index: SeriesIndex, series: DataFrame) -> SeriesIndex:
    """The index with more series; the tree is the one that a bulk build gives.

    Round-robin splits: new words are routed to their leaves by path, counts grow along the paths, and only leaves that
    overflow and buckets that are new are split. Members of all other leaves stay where they are, under the
    leaf ids they had. Balanced splits depend on all members, so there the forest is built again.
    """
    cfg = index.cfg
    full = cut(summarize(series, cfg, keep_values=True))
    more = full.select("series_id", "paa", "word", "bucket")
    summaries = index.summaries.unionByName(more)
    if cfg.split_policy != "round_robin":
        values = index.by_leaf.select("series_id", "word", "values").unionByName(full.select("series_id", "word", "values"))
        nodes, assignments = populate(summaries, cfg)
        return replace(index, summaries=summaries, nodes=nodes, by_leaf=cut(cluster_by_leaf(values, assignments)))
    words = cut(more.groupBy("bucket", "word").agg(F.count(F.lit(1)).alias("n")))
    old = index.nodes.select("bucket", "path", "n_items", "depth", "leaf_id")
    prefixes = words.select("bucket", path_bits(F.col("word"), cfg).alias("b"), "n").select("bucket", F.explode(F.transform(F.sequence(F.lit(0), F.lit(cfg.max_depth)), lambda d: F.substring("b", F.lit(1), d))).alias("path"), "n")
    grown = cut(old.join(prefixes.groupBy("bucket", "path").agg(F.sum("n").alias("more")), ["bucket", "path"], "left").withColumn("total", F.col("n_items") + F.coalesce("more", F.lit(0))))
    over = cut(grown.where((F.col("total") > cfg.theta) & (F.col("depth") < cfg.max_depth) & F.col("leaf_id").isNotNull()).select("bucket", "path", "leaf_id"))
    routed = words.join(old.select("bucket").distinct(), "bucket", "left_anti").withColumn("path", F.lit(""))
    held = index.by_leaf.select("leaf_id", "word").join(small(over), "leaf_id").select("bucket", "path", "word", F.lit(1).cast("bigint").alias("n"))
    routed = routed.unionByName(held.unionByName(assign(words.select("bucket", "word"), more, index.nodes, cfg).join(small(over), "leaf_id").select("bucket", "path", "word", F.lit(1).cast("bigint").alias("n"))).select("bucket", "word", "n", "path"))
    fresh = split_leaves(routed.groupBy("bucket", "path", "word").agg(F.sum("n").alias("n")), cfg)
    kept = grown.join(over.select("bucket", "path"), ["bucket", "path"], "left_anti").select("bucket", "path", F.col("total").alias("n_items"))
    nodes = forest(node_shapes(kept.unionByName(fresh), cfg), cfg)
    # leaves that stay keep their ids; new ones get ids above all old ones
    top = (index.nodes.agg(F.max("leaf_id")).first()[0] or 0) + 1
    ids = old.where("leaf_id is not null").join(over.select("leaf_id"), "leaf_id", "left_anti").select("bucket", "path", F.col("leaf_id").alias("_was"))
    nodes = cut(nodes.join(ids, ["bucket", "path"], "left").withColumn("leaf_id", F.when(F.col("leaf_id").isNotNull(), F.coalesce("_was", F.col("leaf_id") + top))).drop("_was"))
    moved = index.by_leaf.join(small(over.select("leaf_id")), "leaf_id", "left_semi").select("series_id", "word", "values").unionByName(full.select("series_id", "word", "values"))
    bucket = F.aggregate(F.transform("word", lambda x, j: F.call_function("shiftleft", F.call_function("shiftright", x, F.lit(cfg.bits - 1)), F.lit(cfg.w - 1) - j)), F.lit(0), lambda a, x: a + x)
    placed = moved.select("series_id", "word", bucket.alias("bucket"))
    changed = cut(cluster_by_leaf(moved, assign(placed.select("bucket", "word").distinct(), placed, nodes, cfg)))
    return replace(index, summaries=summaries, nodes=nodes, by_leaf=index.by_leaf.join(small(over.select("leaf_id")), "leaf_id", "left_anti").unionByName(changed))
