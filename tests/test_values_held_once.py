"""Values of a collection are held once: what an index and its searches write down doesn't hold them again."""

import os
from urllib.parse import unquote, urlparse

import numpy as np
import pytest

from oracle import duck, spark_rows
from serieslake.config import IndexConfig
from serieslake.operators import baselines as B
from serieslake.operators import index as X
from serieslake.operators import measures as M
from serieslake.operators import search as Q
from serieslake.operators import series as R
from serieslake.operators import staged as G
from serieslake.plans import collections as C
from serieslake.plans.catalog import ORACLE, QUERIES
from serieslake.plans.registry import Tables
from serieslake.session import cut, shared_folder
from serieslake.sources import tables as src

CFG = IndexConfig()


def written(spark):
    top = unquote(urlparse(shared_folder(spark)).path)
    return sum(os.path.getsize(f"{d}/{f}") for d, _, names in os.walk(top) for f in names)


@pytest.fixture(scope="module")
def parts(spark):
    base, ask = R.split_outside(R.parts64(spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet")), 200, 20)
    return cut(base), cut(ask)


def answers(df):
    return [(r.query_id, r.series_id, r.dist) for r in df.orderBy("query_id", "dist", "series_id").collect()]


def test_windows_are_written_as_points(spark):
    """All windows were written down five times over, 2 kB for each event and time."""
    sf = "/root/testdata/sf0.01"
    before = written(spark)
    got = spark_rows(QUERIES["nn1_signal256"](spark, sf))
    assert written(spark) - before < 256 * 8 * 9_745  # the values of the windows, once
    assert got == duck(sf, ORACLE["nn1_signal256"])


@pytest.mark.parametrize("step", [1, 3])
def test_windows_cut_from_points_are_the_windows(spark, step):
    events = Tables(spark, "/root/testdata/sf0.001").events
    points = R.signal_points(events)
    rows = points.where("i % 97 <> 5")  # ids with gaps
    for df in (points, rows, points.limit(0)):
        for n, block in ((8, 10), (16, 64), (16, 4096)):
            got, want = R.window_blocks(df, "i", "running", n, step, block).frame, R.windows(df, "i", "running", n, step, block)
            assert {r[0]: r[1] for r in got.collect()} == {r[0]: r[1] for r in want.collect()}


@pytest.mark.parametrize("unit_bytes", [64 << 20, 20_000])
def test_answers_from_values_held_once(spark, parts, monkeypatch, unit_bytes):
    monkeypatch.setattr(Q, "UNIT_BYTES", unit_bytes)
    base, ask = parts
    plain, held = X.build(base, CFG), X.build(base, CFG, R.plain(base))
    assert "values" not in held.by_leaf.columns and X.tree_equal(plain.nodes, held.nodes)
    assert answers(Q.knn(held, ask, 5)) == answers(Q.knn(plain, ask, 5))
    assert answers(G.ask(G.Run(index=held), ask, 3).answers) == answers(G.ask(G.Run(index=plain), ask, 3).answers)
    assert answers(Q.nn1(B.build(base, CFG, "barrier", raw=R.plain(base)), ask)) == answers(Q.nn1(plain, ask))
    q = Q.Queries.of(ask, CFG)
    none = np.full(len(q.ids), np.inf)
    items = Q._item_bounds(held, q, none, None)
    assert Q.refine(Q.deal(items, held), held, q, none).count() > 0
    assert answers(Q._true_distances(items, held, q, none)) == answers(Q._true_distances(items, plain, q, none))


def test_many_words_find_their_leaves_by_the_splits(parts, monkeypatch):
    """Each word was repeated for each depth at which the forest has leaves."""
    small = X.build(parts[0], CFG)
    want = {(r.series_id, r.leaf_id) for r in small.by_leaf.collect()}
    monkeypatch.setattr(X, "FEW_WORDS", 0)
    for piece in (20_000, 20, 1):
        monkeypatch.setattr(X, "PIECE", piece)
        got = X.build(parts[0], CFG)
        assert X.tree_equal(small.nodes, got.nodes)
        assert {(r.series_id, r.leaf_id) for r in got.by_leaf.collect()} == want


@pytest.mark.parametrize("strategy", ["helping", "barrier"])
def test_indexes_of_noise_runs_write_no_windows(spark, strategy):
    """Each index of w4_hardness held the windows twice more: with the summaries and by leaf."""
    t = Tables(spark, "/root/testdata/sf0.01")
    base, _ = C.parted(t, "signal256")
    before = written(spark)
    ix = C.index(t, "signal256", strategy)
    asked = cut(src.noisy_queries(base, 0.05, 10))
    got = {r.query_id: r.dist for r in Q.knn(ix, asked, 1).collect()}
    shares = M.pruning(ix, asked)
    assert written(spark) - before < 256 * 8 * 9_645  # the values of the collection, once
    assert 0 < shares["pruned_series"] < 1
    assert all(abs(r.dist - got[r.query_id]) < 1e-9 for r in Q.brute_knn(base, asked, 1, C.CONFIGS["signal256"]).collect()) and len(got) == 10


def test_phases_of_the_indexes_write_no_values(spark, monkeypatch):
    """Each of the three indexes of w3_real_collections wrote the values of both collections twice."""
    seen, deal = [], X.cluster_by_leaf
    monkeypatch.setattr(X, "cluster_by_leaf", lambda *a: seen.append(a[0].columns) or deal(*a))
    got = QUERIES["w3_real_collections"](spark, "/root/testdata/sf0.001")
    assert seen == [["series_id", "word"]] * 6 and got.count() == 66
