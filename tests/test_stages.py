"""The four helped stages, and the baselines of each stage, against the plain index and brute force."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from serieslake.config import IndexConfig
from serieslake.operators import baselines as B
from serieslake.operators import index as X
from serieslake.operators import search as Q
from serieslake.operators import staged as G
from serieslake.operators.parts import Fault, Stage, run_parts
from serieslake.sources import tables as src

CFG = replace(IndexConfig(), k_chunks=3, m_groups=2, queues=2, backoff_factor=0.1)


@pytest.fixture(scope="module")
def data(spark):
    walks = src.random_walks(spark, 160, 64)
    base, ask = walks.where("series_id < 150"), walks.where("series_id >= 150").withColumnRenamed("series_id", "query_id")
    truth = sorted((r.query_id, r["rank"], r.series_id) for r in Q.brute_knn(base, ask, 3, CFG).collect())
    return base, ask, truth, X.build(base, CFG)


def answers(run):
    return sorted((r.query_id, r["rank"], r.series_id) for r in run.answers.collect())


def test_four_stages_without_faults(data):
    base, ask, truth, plain = data
    run = G.answer(base, ask, CFG, 3)
    assert answers(run) == truth and X.tree_equal(run.index.nodes, plain.nodes)
    assert list(run.stages) == list(G.STAGES) and run.ledger().where("not done").count() == 0
    slices = G.bucket_slices(run.stages["summarize"])
    assert slices.agg(F.sum("n")).first()[0] == 150 and slices.select("part").distinct().count() == 3


@pytest.mark.parametrize("stage", G.STAGES)
def test_a_dead_worker_is_helped_in_any_stage(data, stage):
    base, ask, truth, _ = data
    run = G.answer(base, ask, CFG, 3, faults={stage: Fault(dead=frozenset([0]))})
    assert answers(run) == truth
    helped = run.ledgers[stage].where("helped").collect()
    assert len(helped) >= 1 and all(r["mode"] == "shared" for r in helped)
    assert run.ledger().where(F.col("stage") != stage).where("helped").count() <= 3


def test_a_late_worker_in_refinement(data):
    base, ask, truth, _ = data
    assert answers(G.answer(base, ask, CFG, 3, faults={"refine": Fault({0: 1.0}), "prune": Fault({1: 1.0})})) == truth


@pytest.mark.parametrize("mode", B.MODES)
def test_modes_give_one_tree_with_a_dead_worker(data, mode):
    base, _, _, plain = data
    run = G.Run()
    raw = G.tree_stage(run, plain.summaries, CFG, mode, Fault(dead=frozenset([0])))
    assert X.tree_equal(raw, plain.nodes)
    rows = run.ledgers["tree"].collect()
    assert len(rows) == (6 if mode == "standard" else 3) and any(r.helped for r in rows)


@pytest.mark.parametrize(("claim", "counted"), [("circle", "checks"), ("counter", "claims"), ("cas", "claims")])
def test_claims_do_every_part(spark, claim, counted):
    df = spark.range(40).withColumnRenamed("id", "k")
    for fault in (None, Fault(dead=frozenset([0]))):
        stage = Stage(spark, claim)
        run_parts(stage, range(4), lambda p: df.where(df.k % 4 == p), owners=2, claim=claim, fault=fault)
        assert stage.read().select("k").distinct().count() == 40 and stage.counts[counted] >= 4
    assert stage.counts["found_undone"] >= (claim != "circle")


def test_consuming_a_stage_leaves_none(spark):
    df = spark.range(9).withColumnRenamed("id", "k")
    stage = Stage(spark, "consumed")
    run_parts(stage, range(3), lambda p: df.where(df.k % 3 == p))
    assert stage.traverse(lambda x, by: x.where(x.k % by == 0), delete=True, params={"by": 2}).count() == 5
    assert stage.read().count() == 0


def test_late_attempts_bring_nothing_back_into_a_consumed_stage(spark):
    """A helper that came back after the stage was consumed marked its part done again, and the elements were there once more."""
    df = spark.range(9).withColumnRenamed("id", "k")
    stage = Stage(spark, "late")
    run_parts(stage, range(3), lambda p: df.where(df.k % 3 == p), helping=False)
    assert stage.traverse(lambda x: x, delete=True).count() == 9
    stage.put(df.where(df.k % 3 == 1), 1, "late")
    stage.mark_done(1, "late", owner=9, helped=True, mode="shared", ms=1, attempts=2)
    assert stage.read().count() == 0
    assert stage.traverse(lambda x: x, delete=True).count() == 0 and stage.read().count() == 0


@pytest.mark.parametrize("flagged", [False, True])
def test_element_wise_trees(data, flagged):
    _, _, _, plain = data
    got = B.trees_one_by_one(plain.summaries, CFG, flagged)
    assert X.tree_equal(got, plain.nodes)
    n = got.agg(*(F.sum(c).alias(c) for c in ("inserts", "splits", "flags"))).first()
    assert n.inserts == 150 and n.splits == plain.nodes.where("not is_leaf").count() and n.flags == n.splits + 300 * flagged


def test_single_queue(data):
    base, ask, truth, plain = data
    run = G.single_queue(G.Run(index=plain), ask, 3)
    assert answers(run) == truth and run.stages["prune"].counts["claims"] >= 3


def test_first_bound_above_ends_a_query_in_a_queue(spark, data):
    _, ask, _, plain = data
    q = Q.Queries.of(ask.limit(1), CFG)
    items = Q.enqueue(Q._item_bounds(plain, q, np.full(1, np.inf), None), 1)
    assert items.count() == 150
    assert Q.refine(items, replace(plain, cfg=replace(CFG, queues=1)), q, np.full(1, np.inf)).count() < 150


def test_insert_touches_only_leaves_that_overflow(data, spark):
    base, ask, truth, plain = data
    half = X.build(base.where("series_id % 3 <> 0"), CFG)
    grown = X.insert_batch(half, base.where("series_id % 3 = 0"))
    assert X.tree_equal(grown.nodes, plain.nodes)
    before = {(r.bucket, r.path): r.leaf_id for r in half.nodes.where("is_leaf").collect()}
    after = {(r.bucket, r.path): r.leaf_id for r in grown.nodes.where("is_leaf").collect()}
    same = before.keys() & after.keys()
    assert len(same) > 10 and all(before[k] == after[k] for k in same) and len(set(after.values())) == len(after)
    counts = {r.leaf_id: r["count"] for r in grown.by_leaf.groupBy("leaf_id").count().collect()}
    assert counts == {r.leaf_id: r.n_items for r in grown.nodes.where("is_leaf and n_items > 0").collect()}
    assert sorted((r.query_id, r["rank"], r.series_id) for r in Q.knn(grown, ask, 3).collect()) == truth
    again = X.insert_batch(grown, src.random_walks(spark, 200, 64).where("series_id >= 160"))
    assert X.tree_equal(again.nodes, X.build(base.unionByName(src.random_walks(spark, 200, 64).where("series_id >= 160")), CFG).nodes)
