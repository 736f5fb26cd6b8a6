"""Trees against their identities, answers against brute force, for every strategy and mode."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from serieslake.config import IndexConfig
from serieslake.operators import baselines as B
from serieslake.operators import index as X
from serieslake.operators import search as Q
from serieslake.operators import series as R
from serieslake.operators.parts import Fault
from serieslake.session import cut
from serieslake.sources import store
from serieslake.sources import tables as src

CFG = IndexConfig()
SERIES = "series_id bigint, values array<double>"


@pytest.fixture(scope="module")
def parts(spark):
    d = spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet")
    base, ask = R.split_outside(R.parts64(d), 200, 20)
    return cut(base), cut(ask)


@pytest.fixture(scope="module")
def truth(parts):
    return pairs(Q.brute_knn(*parts, 5, CFG))


def pairs(df):
    return [(r.query_id, r["rank"], r.series_id, round(r.dist, 6)) for r in df.orderBy("query_id", "rank").collect()]


def test_measured_tree_of_the_walks(spark):
    base, _ = R.split_outside(R.walk64(spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet")), 500)
    r = X.build(base, CFG).stats().first()
    assert (r.roots, r.nodes, r.leaves, r.empty_leaves, r.max_depth, r["items"]) == (99, 127, 113, 0, 5, 400)


def test_level_wise_build_equals_the_small_one(parts, monkeypatch):
    small = X.build(parts[0], CFG)
    monkeypatch.setattr(X, "FEW_WORDS", 0)
    monkeypatch.setattr(X, "STRIDE", 3)
    assert X.tree_equal(small.nodes, X.build(parts[0], CFG).nodes)


def test_tree_identities(parts):
    for policy in ("round_robin", "balanced"):
        ix = X.build(parts[0], replace(CFG, split_policy=policy))
        n = {(r.bucket, r.path): r for r in ix.nodes.collect()}
        for (b, p), r in n.items():
            if r.is_leaf:
                assert (b, p + "0") not in n and (r.n_items <= CFG.theta or r.depth == CFG.max_depth)
            else:
                assert n[b, p + "0"].n_items + n[b, p + "1"].n_items == r.n_items
                assert r.left_nodes == sum(1 for c, q in n if c == b and q.startswith(p + "0"))
        for b in {b for b, _ in n}:
            order = sorted((r for (c, _), r in n.items() if c == b), key=lambda r: r.inorder)
            assert [r.inorder for r in order] == list(range(1, len(order) + 1))
            keys = [r.path.translate(str.maketrans("01", "az")) + "m" for r in order]
            assert keys == sorted(keys)
        leaves = sorted(r.leaf_id for r in n.values() if r.is_leaf)
        assert leaves == list(range(len(leaves)))
        assert ix.by_leaf.count() == parts[0].count() == sum(r.n_items for r in n.values() if r.is_leaf)
        assert {(r.bucket, r.total) for r in X.tree_size(ix.nodes).collect()} == {(b, sum(1 for c, _ in n if c == b)) for b in {b for b, _ in n}}
        by = {r.leaf_id: r for r in n.values() if r.is_leaf}
        for r in ix.by_leaf.collect():  # a leaf covers its words
            leaf = by[r.leaf_id]
            assert all(x >> (8 - u) == s for x, u, s in zip(r.word, leaf.bits, leaf.syms))


@pytest.mark.parametrize("options", [{}, {"levelwise": True}, {"cfg": {"seed_how": "none"}}, {"cfg": {"seed_how": "best_lb"}}, {"cfg": {"waves": "one"}}, {"cfg": {"split_policy": "balanced"}}, {"cfg": {"queues": 1}}])
def test_knn_is_exact(parts, truth, options):
    cfg = replace(CFG, **options.pop("cfg", {}))
    assert pairs(Q.knn(X.build(parts[0], cfg), parts[1], 5, first_wave=4, **options)) == truth


@pytest.mark.parametrize("strategy", B.STRATEGIES)
def test_strategies_agree(parts, truth, strategy):
    assert pairs(Q.knn(B.build(parts[0], CFG, strategy), parts[1], 5)) == truth


@pytest.mark.parametrize("mode", B.MODES)
def test_modes_agree_under_delay(parts, mode):
    assert X.tree_equal(B.build(parts[0], CFG, mode=mode, fault=Fault({0: 0.5})).nodes, X.build(parts[0], CFG).nodes)


def test_other_answers(parts, truth):
    ix = X.build(parts[0], CFG)
    near = {(q, s) for q, r, s, d in truth if r == 1}
    assert {(r.query_id, r.series_id) for r in Q.nn1(ix, parts[1]).collect()} == near
    assert pairs(Q.scan_knn(ix, parts[1], 5)) == truth
    eps = sorted(d for _, r, _, d in truth if r == 3)[10]
    got = Q.range_search(ix, parts[1], eps).collect()
    want = [r for r in Q.brute_knn(*parts, 1000, CFG).collect() if r.dist <= eps]
    assert {(r.query_id, r.series_id) for r in got} == {(r.query_id, r.series_id) for r in want}
    first = {r.query_id: r.dist for r in Q.approx_nn(ix, parts[1]).collect()}
    assert all(first[q] >= d - 1e-6 for q, r, _, d in truth if r == 1)


def frame(spark, rows):
    return spark.createDataFrame([(i, [float(x) for x in v]) for i, v in rows], SERIES)


def test_ties_copies_members_and_flat_series(spark):
    rng = np.random.default_rng(5)
    walks = np.cumsum(rng.standard_normal((30, 64)), axis=1)
    rows = [(i, v) for i, v in enumerate(walks)] + [(100 + k, walks[3]) for k in range(40)] + [(200, np.full(64, 7.0)), (201, np.zeros(64))]
    ix = X.build(frame(spark, rows), CFG)
    ask = frame(spark, [(0, walks[3]), (1, np.ones(64))]).withColumnRenamed("series_id", "query_id")
    got = {r.query_id: (r.series_id, r.dist) for r in Q.nn1(ix, ask).collect()}
    assert got[0] == (3, 0.0) and got[1] == (200, 0.0)
    over = ix.nodes.where("is_leaf and n_items > 16").collect()
    assert [r.depth for r in over] == [CFG.max_depth]  # equal words can't be split


def test_empty_collection_and_empty_queries(spark, parts):
    none = parts[0].limit(0)
    ix = X.build(none, CFG)
    assert Q.nn1(ix, parts[1]).count() == 0
    assert Q.nn1(X.build(parts[0], CFG), parts[1].limit(0)).count() == 0


def test_insert_equals_bulk(parts, truth, spark, tmp_path):
    base, ask = parts
    half = X.build(base.where("series_id % 2 = 0"), CFG)
    assert X.tree_equal(X.insert_batch(half, base.where("series_id % 2 = 1")).nodes, X.build(base, CFG).nodes)
    path = f"file://{tmp_path}/ix"
    store.save(half, path)
    assert store.append(spark, path, base.where("series_id % 2 = 1"), 4)
    assert not store.append(spark, path, base.where("series_id % 2 = 1"), 4)
    assert pairs(Q.knn(store.load(spark, path), ask, 5)) == truth


def test_self_nearest(parts):
    got = {r.query_id: r.series_id for r in Q.self_nn(X.build(parts[0], CFG)).collect()}
    two = Q.brute_knn(parts[0], parts[0].withColumnRenamed("series_id", "query_id"), 2, CFG).where("query_id <> series_id").groupBy("query_id").agg(F.min(F.struct("dist", "series_id")).alias("m")).collect()
    assert got == {r.query_id: r.m.series_id for r in two}


def test_plans_prune_columns_and_share_no_raw_values(parts):
    ix = X.build(parts[0], CFG)
    q = Q.Queries.of(parts[1], CFG)
    plan = Q.prune(ix, q, np.full(len(q.ids), 1.0))._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoop" not in plan


def test_validate_and_generators(spark):
    rows = [(1, [1.0, 2.0]), (2, None), (3, [1.0]), (4, [1.0, None]), (5, [float("nan"), 1.0]), (None, [1.0, 2.0])]
    ok, bad = src.validate_series(spark.createDataFrame(rows, SERIES), 2)
    assert [r.series_id for r in ok.collect()] == [1]
    assert {r.series_id: r.reason for r in bad.collect()} == {2: "null array", 3: "wrong length", 4: "null point", 5: "non-finite point", None: "null id"}
    steps = np.diff(np.array([r["values"] for r in src.random_walks(spark, 200, 64).collect()]), axis=1)
    assert abs(steps.mean()) < 0.05 and abs(steps.std() - 1) < 0.05
    walks = src.random_walks(spark, 50, 64)
    noisy = src.noisy_queries(walks, 0.0, 10).collect()
    assert len(noisy) == 10 and {r.query_id for r in noisy} == {r.query_id for r in src.noisy_queries(walks, 0.1, 10).collect()}


def test_builders_on_small_frames(spark):
    df = spark.createDataFrame([(i, float(i * i % 7)) for i in range(50)], "i bigint, v double")
    got = {r.series_id: r["values"] for r in R.windows(df, "i", "v", 8, 3, block=10).collect()}
    v = [float(i * i % 7) for i in range(50)]
    assert got == {i + 7: v[i : i + 8] for i in range(0, 43, 3)}
    run = {r.i: r.running for r in R.prefix_sum(df, "i", "v", block=7).collect()}
    assert all(abs(run[i] - sum(v[: i + 1])) < 1e-9 for i in range(50))
    dense = {r.v2: r.i for r in R.dense_index(df.select((F.col("i") * 3 + 1).alias("v2")), "v2").collect()}
    assert dense == {i * 3 + 1: i for i in range(50)}
    gaps = spark.createDataFrame([(1, 0, 2.0), (1, 3, 5.0)], "k bigint, s int, x double")
    for fill, want in (("zero", [2, 0, 0, 5, 0]), ("forward", [2, 2, 2, 5, 5]), ("linear", [2, 3, 4, 5, 5])):
        assert R.slots(gaps, "k", F.col("s"), F.col("x"), 5, fill).first()["values"] == want
    one = frame(spark, [(1, [1, 2, 4, 8])])
    assert R.normalise(one, "difference", 4).first()["values"] == [0, 1, 2, 4]
    assert R.normalise(one, "minmax", 4).first()["values"][-1] == 1
    assert R.to_wide(R.to_long(one), 4).first()["values"] == [1, 2, 4, 8]
    assert one.select(R.cumsum_column(F.col("values")).alias("c")).first().c == [1, 3, 7, 15]
