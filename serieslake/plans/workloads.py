"""The experiments on the stand-in collections: each returns its measures as rows.

Real runs compare strategies in Spark; what hinges on atomic instructions or on more workers than
this machine has is replayed by the simulator, and such rows say so in their method's name.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import baselines as B
from ..operators import measures as M
from ..operators import search as Q
from ..operators import simulate as Z
from ..operators import staged as G
from ..operators.parts import Fault
from ..session import cut
from ..sources import tables as src
from . import collections as C
from .registry import Tables, query

INDEXES = ("helping", "barrier", "leaf_lock")
UNITS = [1.0 + (k * 7 % 5) / 4 for k in range(96)]


def _run(t: Tables, workload: str, name: str, methods, param="", queries: DataFrame | None = None, reps: int = 1, **options) -> M.Recorder:
    base, ask = C.parted(t, name)
    rec = M.Recorder()
    for m in methods:
        M.run_phases(rec, workload, param, base, ask if queries is None else queries, C.CONFIGS[name], m, reps=reps, **options)
    return rec


def _helped(rec: M.Recorder, t: Tables, workload: str, name: str, param, stages, faults=None, mode: str = "leaf", label: str = "helping", **options) -> DataFrame:
    """Times the named helped stages over what the plain index has for the others; the answers of the last two."""
    base, asked = C.parted(t, name)
    ix, faults, run = C.index(t, name), faults or {}, G.Run()
    if "summarize" in stages:
        rec.timed(workload, label, param, 0, "summarize_s", lambda: G.summaries_stage(run, base, ix.cfg, faults.get("summarize"), **options))
    if "tree" in stages:
        rec.timed(workload, label, param, 0, "tree_s", lambda: M.materialize(G.tree_stage(run, ix.summaries, ix.cfg, mode, faults.get("tree"), **options)))
    run.index = ix
    if "refine" in stages:
        rec.timed(workload, label, param, 0, "query_s", lambda: G.ask(run, asked, 1, faults, **options))
    for stage, ledger in run.ledgers.items():
        got = M.load_balance(ledger).first()
        rec.put(workload, label, param, 0, f"{stage}_helps", got.helps or 0)
        rec.put(workload, label, param, 0, f"{stage}_copies", got.wasted or 0)
    return run.answers


ALL = G.STAGES


@query()
def w1_workers(t: Tables):
    """Workers: phases of the helping index with 1, 2 and 4 owners in Spark, and makespans of the three indexes for 1 to 24
    workers, replayed over uneven parts."""
    rec = M.Recorder()
    for w in (1, 2, 4):
        _helped(rec, t, "workers", "walk64", w, ALL, owners=w)
    for p in ("helping", "barrier", "leaf_lock"):
        for w in (1, 2, 4, 8, 12, 16, 20, 24):
            rec.put("workers", f"{p} (replayed)", w, 0, "makespan", Z.simulate(UNITS, p, w).makespan)
    return rec.df(t.spark)


@query()
def w2_random_size(t: Tables):
    """Size: generated walks of growing number; all phases of the three indexes."""
    rec = M.Recorder()
    cfg = replace(C.CONFIGS["walk64"], theta=100)
    for n in (2_000, 8_000):
        walks = src.random_walks(t.spark, n + 100, 64)
        base, ask = walks.where(F.col("series_id") < n), walks.where(F.col("series_id") >= n).withColumnRenamed("series_id", "query_id")
        for m in INDEXES:
            M.run_phases(rec, "size", n, base, ask, cfg, m)
    return rec.df(t.spark)


@query()
def w3_real_collections(t: Tables):
    """The smooth and the skewed collection under the three indexes."""
    rec = _run(t, "signal256", "signal256", INDEXES, raw=C.members(t, "signal256"))
    rec.rows += _run(t, "parts64", "parts64", INDEXES, raw=C.members(t, "parts64")).rows
    return rec.df(t.spark)


@query()
def w4_hardness(t: Tables):
    """Members with noise: harder queries prune less. The indexes are built once; only the queries change."""
    rec = M.Recorder()
    base, _ = C.parted(t, "signal256")
    for sigma in (0.01, 0.02, 0.05, 0.1):
        asked = cut(src.noisy_queries(base, sigma, 100))
        for m in ("helping", "barrier"):
            ix = C.index(t, "signal256", m)
            rec.timed("hardness", m, sigma, 0, "query_s", lambda ix=ix, asked=asked: Q.knn(ix, asked, 1))
        for name, v in M.pruning(ix, asked).items():
            rec.put("hardness", "any", sigma, 0, name, v)
    return rec.df(t.spark)


@query()
def w5_tree_modes(t: Tables):
    """The tree build under its four modes, on the skewed collection, undisturbed and with a late worker."""
    rec = M.Recorder()
    for late in (0.0, 1.0):
        for mode in ("leaf", "subtree", "standard", "private"):
            _helped(rec, t, "tree modes", "parts64", late, ("tree",), {"tree": Fault(delays={0: late})} if late else None, mode, f"{mode}-mode")
    return rec.df(t.spark)


@query()
def w6_stage_baselines(t: Tables):
    """Against the baselines of each stage; total, by phase, and what sharing cost."""
    return _run(t, "stage baselines", "walk64", ("helping", "static_split", "counter_claim", "cas_claim", "direct_insert")).df(t.spark)


@query()
def w6a_summarization(t: Tables):
    """Summarization alone: helped chunks laid out by bucket against one buffer under flags, counter and claims."""
    rec = M.Recorder()
    base, _ = C.parted(t, "walk64")
    for m in ("helping", "static_split", "counter_claim", "cas_claim"):
        run = G.Run()
        rec.timed("summarization", m, "", 0, "summarize_s", lambda m=m, run=run: B.summarize(base, C.CONFIGS["walk64"], m, run=run))
        for what, n in run.stages["summarize"].counts.items():
            rec.put("summarization", m, "", 0, what, n)
    return rec.df(t.spark)


@query()
def w6b_tree(t: Tables):
    """Tree population alone: helped pieces against element-wise inserts with and without flags."""
    rec = M.Recorder()
    words, cfg = C.index(t, "walk64").summaries, C.CONFIGS["walk64"]
    rec.timed("tree population", "helping", "", 0, "tree_s", lambda: M.materialize(B.tree(words, cfg, "helping")))
    for flagged in (False, True):
        name = "element-wise, flagged" if flagged else "element-wise"
        got = rec.timed("tree population", name, "", 0, "tree_s", lambda flagged=flagged: B.trees_one_by_one(words, cfg, flagged).agg(F.sum("inserts"), F.sum("splits"), F.sum("flags")).first())
        for what, n in zip(("inserts", "splits", "flags"), got, strict=True):
            rec.put("tree population", name, "", 0, what, n)
    return rec.df(t.spark)


@query()
def w6c_queries(t: Tables):
    """Query answering alone: helped queues against one queue that is emptied by delete-min."""
    rec = M.Recorder()
    ix, (_, ask) = C.index(t, "walk64"), C.parted(t, "walk64")
    rec.timed("query answering", "helping", "", 0, "query_s", lambda: G.ask(G.Run(index=ix), ask))
    run = rec.timed("query answering", "single queue", "", 0, "query_s", lambda: G.single_queue(G.Run(index=ix), ask))
    for what, n in run.stages["prune"].counts.items():
        rec.put("query answering", "single queue", "", 0, what, n)
    return rec.df(t.spark)


@query()
def w7_one_delayed(t: Tables):
    """One late worker, growing delay, in summarization, tree, pruning and refinement: in Spark with helped ledgers, and
    replayed for the barrier."""
    rec = M.Recorder()
    for stage, timed in (("summarize", ("summarize",)), ("tree", ("tree",)), ("prune", ("refine",)), ("refine", ("refine",))):
        for d in (0.0, 2.0):
            _helped(rec, t, f"one delayed in {stage}", "walk64", d, timed, {stage: Fault(delays={0: d})})
    for p in ("barrier", "helping"):
        for d in (0, 5, 10, 20, 40):
            rec.put("one delayed", f"{p} (replayed)", d, 0, "makespan", Z.simulate(UNITS, p, 8, {0: float(d)}).makespan)
    return rec.df(t.spark)


@query()
def w8_many_delayed(t: Tables):
    cases = [dict(scenario="many delayed", policy=p, workers=24, delayed=k, delay=20.0) for p in ("barrier", "helping") for k in (0, 1, 4, 8, 16, 23)]
    return Z.scenarios(t.spark, UNITS, cases)


@query()
def w9_failures(t: Tables):
    """Dead workers for good: the answers of a build whose first owner dies, and replayed makespans."""
    rec = M.Recorder()
    base, ask = C.parted(t, "walk64")
    truth = Q.brute_knn(base, ask, 1, C.CONFIGS["walk64"])
    for dead in (0, 1):
        got = _helped(rec, t, "failures", "walk64", dead, ALL, {s: Fault(dead=frozenset(range(dead))) for s in ALL})
        rec.put("failures", "helping", dead, 0, "recall", M.recall(got, truth).first()[0])
    for f in (0, 1, 4, 8, 16, 23):
        rec.put("failures", "helping (replayed)", f, 0, "makespan", Z.simulate(UNITS, "helping", 24, dead=frozenset(range(f))).makespan)
        rec.put("failures", "helping, live workers alone (replayed)", f, 0, "makespan", Z.simulate(UNITS, "helping", 24 - f).makespan)
    return rec.df(t.spark)


@query("SELECT CAST(100 AS BIGINT) AS queries, CAST(0 AS BIGINT) AS members")
def w10_outside_queries(t: Tables):
    base, ask = C.parted(t, "walk64")
    inside = ask.join(base.withColumnRenamed("series_id", "query_id"), "query_id", "left_semi")
    return ask.agg(F.count(F.lit(1)).alias("queries")).crossJoin(inside.agg(F.count(F.lit(1)).alias("members")))


@query()
def w11_heavy_bucket(t: Tables):
    """Many workers inside the heaviest bucket."""
    base, ask = C.parted(t, "parts64")
    from ..operators import index as X

    words = X.summarize(base, C.CONFIGS["parts64"])
    top = words.groupBy("bucket").count().orderBy(F.desc("count"), "bucket").first()[0]
    heavy = base.join(words.where(F.col("bucket") == top).select("series_id"), "series_id", "left_semi")
    rec = M.Recorder()
    for m in INDEXES:
        M.run_phases(rec, "heavy bucket", top, heavy, ask, C.CONFIGS["parts64"], m)
    return rec.df(t.spark)


@query()
def w12_no_structure(t: Tables):
    """Vectors without local structure: nothing is pruned and the index does what a scan does."""
    rec = _run(t, "no structure", "vec64", ("level",))
    base, ask = C.parted(t, "vec64")
    rec.timed("no structure", "scan", "", 0, "query_s", lambda: M.materialize(Q.brute_knn(base, ask, 1, C.CONFIGS["vec64"])))
    return rec.df(t.spark)
