"""What runs are judged by: times of the phases, pruning, balance, copies, exactness."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import cut, shared_folder, stored
from ..sources.tables import materialize
from . import baselines as B
from . import index as X
from . import search as Q
from . import staged as G
from .parts import Fault
from .series import Raw

MEASURES = T.StructType([T.StructField("workload", T.StringType()), T.StructField("method", T.StringType()), T.StructField("param", T.StringType()), T.StructField("rep", T.IntegerType()), T.StructField("measure", T.StringType()), T.StructField("value", T.DoubleType())])


@dataclass
class Recorder:
    """Rows of (workload, method, param, rep, measure, value)."""

    rows: list[tuple] = field(default_factory=list)

    def put(self, workload: str, method: str, param, rep: int, measure: str, value: float) -> None:
        self.rows.append((workload, method, str(param), rep, measure, float(value)))

    def timed(self, workload: str, method: str, param, rep: int, phase: str, action: Callable):
        begun = time.perf_counter()
        out = action()
        self.put(workload, method, param, rep, phase, time.perf_counter() - begun)
        return out

    def df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, MEASURES)


def summary(measures: DataFrame) -> DataFrame:
    """Mean and deviation over the repetitions."""
    return measures.groupBy("workload", "method", "param", "measure").agg(F.avg("value").alias("mean"), F.stddev_pop("value").alias("dev"), F.count(F.lit(1)).alias("reps"))


def run_phases(rec: Recorder, workload: str, param, series: DataFrame, queries: DataFrame, cfg, strategy: str, mode: str | None = None, reps: int = 1, fault: Fault | None = None, k: int = 1, faults: dict[str, Fault] | None = None, workers: int = 4, raw: Raw | None = None) -> DataFrame:
    """Times summarization, tree and query answering of a method and their sum; returns the last answers. ``faults``
    names a stage each (``fault`` alone: summarization); helps, copies and the counts of claims are recorded too. With ``raw``
    the values stay there."""
    answers = None
    name = mode and f"{mode}-mode" or strategy
    faults = faults or ({"tree" if mode else "summarize": fault} if fault else {})
    for rep in range(reps):
        run = G.Run()
        full = rec.timed(workload, name, param, rep, "summarize_s", lambda run=run: B.summarize(series, cfg, strategy, workers, faults.get("summarize"), run, raw is None))
        summaries = full.select("series_id", "paa", "word", "bucket")

        def tree(full=full, summaries=summaries, run=run):
            counts = G.tree_stage(run, summaries, cfg, mode, faults.get("tree")) if mode else B.tree(summaries, cfg, strategy, fault=faults.get("tree"), run=run, workers=workers)
            nodes, at = X.populate(summaries, cfg, None if counts is None else X.node_shapes(counts, cfg))
            by_leaf = stored(X.cluster_by_leaf(full.select(*X.VALUED[: 3 if raw is None else 2]), at))
            return X.SeriesIndex(cfg, summaries, nodes, by_leaf, raw)

        run.index = rec.timed(workload, name, param, rep, "tree_s", tree)
        answers = rec.timed(workload, name, param, rep, "query_s", lambda run=run: ask(run, queries, strategy, k, faults))
        rec.put(workload, name, param, rep, "total_s", sum(r[5] for r in rec.rows[-3:]))
        for m, v in pruning(run.index, queries, k).items():
            rec.put(workload, name, param, rep, m, v)
        for stage, ledger in run.ledgers.items():
            got = load_balance(ledger).first()
            rec.put(workload, name, param, rep, f"{stage}_helps", got.helps or 0)
            rec.put(workload, name, param, rep, f"{stage}_copies", got.wasted or 0)
        for stage, held in run.stages.items():
            for what, n in held.counts.items():
                rec.put(workload, name, param, rep, f"{stage}_{what}", n)
    return answers


def ask(run: G.Run, queries: DataFrame, strategy: str, k: int = 1, faults: dict[str, Fault] | None = None) -> DataFrame:
    """Answers by the way a strategy has to prune and refine."""
    if strategy == "helping":
        return G.ask(run, queries, k, faults).answers
    if strategy in B.CLAIMS:
        return G.single_queue(run, queries, k, (faults or {}).get("prune")).answers
    return Q.knn(run.index, queries, k)


def pruning(index: X.SeriesIndex, queries: DataFrame, k: int = 1) -> dict[str, float]:
    """Shares of leaves and of members that bounds rule out at the first best-so-far, and bound computations a query."""
    q = Q.Queries.of(queries, index.cfg)
    bsf = Q._kth(Q.top_k(Q.seed(index, q, "leaf", k), k), q, k)
    leaves = index.leaves.count()
    kept = Q.asked_leaves(Q.prune(index, q, bsf), True)
    alive, items = kept.agg(F.sum(F.size("asked"))).first()[0] or 0, Q._item_bounds(index, q, bsf, kept).count()
    members, asked = index.by_leaf.count(), max(1, len(q.ids))
    return {"pruned_leaves": 1 - alive / max(1, leaves * asked), "pruned_series": 1 - items / max(1, members * asked), "true_distances_a_query": items / asked}


def recall(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """Share of true neighbours found; 1 for an exact method."""
    hit = truth.select("query_id", "series_id").join(answers.select("query_id", "series_id").withColumn("hit", F.lit(1)), ["query_id", "series_id"], "left")
    return hit.agg(F.avg(F.coalesce("hit", F.lit(0)).cast("double")).alias("recall"))


def queue_balance(queued: DataFrame) -> DataFrame:
    return queued.groupBy("queue_id").agg(F.count(F.lit(1)).alias("n")).agg((F.max("n") / F.avg("n")).alias("largest_over_mean"))


def load_balance(ledger: DataFrame) -> DataFrame:
    return ledger.agg((F.max("ms") / F.avg("ms")).alias("slowest_over_mean"), F.sum(F.col("helped").cast("bigint")).alias("helps"), (F.sum("attempts") - F.count(F.lit(1))).alias("wasted"))


def speed_up(measures: DataFrame) -> DataFrame:
    """Against the fewest workers of each method and measure; param holds the number of workers."""
    w = Window.partitionBy("workload", "method", "measure").orderBy(F.col("param").cast("int"))
    first, workers = F.first("mean").over(w), F.col("param").cast("int")
    return summary(measures).withColumn("speed_up", first / F.col("mean")).withColumn("efficiency", F.col("speed_up") * F.first(workers).over(w) / workers)


def index_bytes(index: X.SeriesIndex, folder: str | None = None) -> dict[str, float]:
    """Bytes of the tables as Parquet files, and the share of summaries and nodes in the values; written to the shared folder."""
    spark, out = index.nodes.sparkSession, {}
    folder = folder or f"{shared_folder(spark)}/sizes-{uuid.uuid4()}"
    at = spark._jvm.org.apache.hadoop.fs.Path
    fs = at(folder).getFileSystem(spark._jsc.hadoopConfiguration())
    for name, df in (("raw", index.values), ("summaries", index.summaries.select("series_id", "word")), ("nodes", index.nodes)):
        df.write.parquet(f"{folder}/{name}")
        out[name] = float(fs.getContentSummary(at(f"{folder}/{name}")).getLength())
    fs.delete(at(folder), True)
    return out | {"share": (out["summaries"] + out["nodes"]) / out["raw"] if out["raw"] else float(np.nan)}


__all__ = ["Fault", "MEASURES", "Recorder", "materialize", "pruning", "recall", "run_phases", "speed_up", "summary"]
