"""Summaries, trees, answers, ledger, simulator and sources as queries, with SQL that computes the same."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import summaries as S
from ..functions.registry import register
from ..operators import baselines as B
from ..operators import index as X
from ..operators import measures as M
from ..operators import parts as P
from ..operators import search as Q
from ..operators import series as R
from ..operators import simulate as Z
from ..operators import staged as G
from ..session import shared_folder
from ..sources import tables as src
from . import collections as C
from .registry import Tables, query

W, THETA, DEPTH = 8, 16, 56


# --- SQL fragments ------------------------------------------------------------------------------

_RAW = {
    "walk64": "SELECT vec_id AS series_id, list_transform(range(1, 65), lambda i: list_sum(list_transform(embedding[1:i], lambda x: 8.0 * CAST(x AS DOUBLE)))) AS v FROM embeddings",
    "vec64": "SELECT vec_id AS series_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings",
    "parts64": """SELECT k AS series_id, list_transform(range(1, 65), lambda i: list_sum(m[1:i])) AS v FROM (
  SELECT g.k, list(coalesce(s.r, 0.0) ORDER BY g.s) AS m FROM (
    SELECT k, unnest(range(0, 64)) AS s FROM (SELECT DISTINCT l_partkey AS k FROM lineitem WHERE (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 BETWEEN 0 AND 63)) g
  LEFT JOIN (SELECT l_partkey AS k, (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS s, round(sum(l_extendedprice * (1 - l_discount)), 4) AS r FROM lineitem GROUP BY ALL) s
  ON g.k = s.k AND g.s = s.s GROUP BY g.k)""",
    "signal256": """SELECT event_id AS series_id, v FROM (
  SELECT event_id, list(running) OVER (ORDER BY event_id ROWS 255 PRECEDING) AS v FROM (
    SELECT event_id, round(sum(coalesce(value, 0.0) - 50.0) OVER (ORDER BY event_id ROWS UNBOUNDED PRECEDING), 6) AS running FROM events)) WHERE len(v) = 256""",
}
_POINTS = "[" + ", ".join(repr(p) for p in S.breakpoints(8)) + "]"


def ctes(name: str, z: bool = True, w: int = W) -> str:
    """raw(series_id, v), z(series_id, z), s(series_id, z, paa, word, bucket)."""
    n = C.CONFIGS[name].n
    size = n // w
    norm = "CASE WHEN sd < 1e-8 THEN list_transform(v, lambda x: 0.0) ELSE list_transform(v, lambda x: (x - m) / sd) END" if z else "v"
    return f"""raw AS MATERIALIZED ({_RAW[name]}),
z AS MATERIALIZED (SELECT series_id, {norm} AS z FROM (
  SELECT series_id, v, m, sqrt(list_sum(list_transform(v, lambda x: (x - m) * (x - m))) / {n}) AS sd FROM (SELECT series_id, v, list_sum(v) / {n} AS m FROM raw))),
p AS MATERIALIZED (SELECT series_id, z, list_transform(range(0, {w}), lambda j: round(list_sum(z[j * {size} + 1 : j * {size} + {size}]) / {size}, 9)) AS paa FROM z),
s AS MATERIALIZED (SELECT *, CAST(list_sum(list_transform(range(0, {w}), lambda j: (word[j + 1] >> 7) << ({w - 1} - j))) AS INTEGER) AS bucket FROM (
  SELECT *, list_transform(paa, lambda x: CAST(len(list_filter({_POINTS}, lambda b: b <= x)) AS INTEGER)) AS word FROM p))"""


_SPLIT = """cnt AS (SELECT greatest(count(*) // 100, 1) AS m FROM raw),
base AS MATERIALIZED (SELECT s.* FROM s, cnt WHERE series_id % m <> m - 1),
ask AS MATERIALIZED (SELECT series_id AS query_id, z, paa, word FROM s, cnt WHERE series_id % m = m - 1)"""
_SPLIT_WINDOWS = """top AS (SELECT max(series_id) AS t FROM raw),
base AS MATERIALIZED (SELECT s.* FROM s, top WHERE series_id <= t - 100 - 255),
ask AS MATERIALIZED (SELECT series_id AS query_id, z, paa, word FROM s, top WHERE series_id > t - 100)"""

_NODES = f"""bits AS (SELECT bucket, list_aggregate(list_transform(range(0, {DEPTH}), lambda d: CAST((word[d % {W} + 1] >> (6 - d // {W})) & 1 AS VARCHAR)), 'string_agg', '') AS b FROM base),
counts AS MATERIALIZED (SELECT bucket, b[1:d] AS path, count(*) AS n FROM (SELECT bucket, b, unnest(range(0, {DEPTH + 1})) AS d FROM bits) GROUP BY ALL),
nodes AS MATERIALIZED (
  SELECT bucket, '' AS path, n AS n_items FROM counts WHERE path = ''
  UNION ALL
  SELECT p.bucket, p.path || x.side, coalesce(c.n, 0) FROM counts p CROSS JOIN (VALUES ('0'), ('1')) x(side)
  LEFT JOIN counts c ON c.bucket = p.bucket AND c.path = p.path || x.side WHERE p.n > {THETA} AND length(p.path) < {DEPTH}),
ranked AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY bucket ORDER BY translate(path, '01', 'az') || 'm') AS inorder,
  n_items <= {THETA} OR length(path) = {DEPTH} AS is_leaf FROM nodes)"""


def sql(name: str, body: str, tree: bool = False, split: str | None = _SPLIT, z: bool = True) -> str:
    parts = [ctes(name, z)] + ([split] if split else []) + ([_NODES] if tree else [])
    return "WITH " + ",\n".join(parts) + "\n" + body


def _nearest(k: int) -> str:
    return f"""SELECT query_id, series_id, round(dist, 6) AS dist, CAST(r AS BIGINT) AS rank FROM (
  SELECT query_id, series_id, dist, row_number() OVER (PARTITION BY query_id ORDER BY dist, series_id) AS r
  FROM (SELECT query_id, series_id, list_distance(a.z, b.z) AS dist FROM ask a, base b)) WHERE r <= {k}"""


def _word(col: str = "word"):
    return F.array_join(F.transform(col, lambda x: x.cast("string")), ",")


def _summaries(t: Tables, name: str) -> DataFrame:
    return X.summarize(C.series(t, name), C.CONFIGS[name])


def _answers(df: DataFrame) -> DataFrame:
    rank = F.col("rank") if "rank" in df.columns else F.lit(1)
    return df.select("query_id", "series_id", F.round("dist", 6).alias("dist"), rank.cast("bigint").alias("rank"))


# --- builders -----------------------------------------------------------------------------------


@query(f"SELECT series_id, CAST(generate_subscripts(v, 1) - 1 AS BIGINT) AS pos, round(unnest(v), 6) AS value FROM ({_RAW['walk64']})")
def walk64_points(t: Tables):
    return R.to_long(C.series(t, "walk64")).select("series_id", F.col("pos").cast("bigint").alias("pos"), F.round("value", 6).alias("value"))


@query(f"SELECT series_id, round(v[1], 4) AS first, round(v[64], 4) AS last, round(list_sum(v), 4) AS total FROM ({_RAW['parts64']})")
def parts64_series(t: Tables):
    v = F.col("values")
    return C.series(t, "parts64").select("series_id", F.round(F.get(v, F.lit(0)), 4).alias("first"), F.round(F.get(v, F.lit(63)), 4).alias("last"), F.round(F.aggregate(v, F.lit(0.0), lambda a, x: a + x), 4).alias("total"))


@query(f"SELECT series_id, round(v[1], 4) AS first, round(v[256], 4) AS last, round(list_max(v), 4) AS most FROM ({_RAW['signal256']})")
def signal_windows(t: Tables):
    v = F.col("values")
    return C.series(t, "signal256").select("series_id", F.round(F.get(v, F.lit(0)), 4).alias("first"), F.round(F.get(v, F.lit(255)), 4).alias("last"), F.round(F.array_max(v), 4).alias("most"))


@query("SELECT event_id, round(list_sum(v), 4) AS total FROM (SELECT event_id, list(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 31 PRECEDING) AS v FROM events) WHERE len(v) = 32")
def user32_windows(t: Tables):
    return C.series(t, "user32").select(F.col("series_id").alias("event_id"), F.round(F.aggregate("values", F.lit(0.0), lambda a, x: a + x), 4).alias("total"))


@query("""SELECT g.k AS user_id, CAST(g.s AS BIGINT) AS day, round(coalesce(e.v, 0.0), 4) AS value FROM (
  SELECT k, unnest(range(0, 30)) AS s FROM (SELECT DISTINCT user_id AS k FROM events WHERE ts < TIMESTAMP '2024-01-31' AND value IS NOT NULL)) g
LEFT JOIN (SELECT user_id AS k, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS s, round(sum(value), 4) AS v FROM events GROUP BY ALL) e ON e.k = g.k AND e.s = g.s""")
def events_grid_fill(t: Tables):
    day = F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date"))
    grid = R.slots(t.events.where("value is not null"), "user_id", day, F.col("value"), 30)
    return R.to_long(grid).select(F.col("series_id").alias("user_id"), F.col("pos").cast("bigint").alias("day"), F.round("value", 4).alias("value"))


@query("SELECT event_id, round(sum(coalesce(value, 0.0) - 50.0) OVER (ORDER BY event_id ROWS UNBOUNDED PRECEDING), 4) AS running FROM events")
def prefix_sum_events(t: Tables):
    return R.signal_points(t.events).select(F.col("i").alias("event_id"), F.round("running", 4).alias("running"))


@query("""WITH day AS (SELECT CAST(o_orderdate AS DATE) AS d, round(sum(o_totalprice), 4) AS total FROM orders GROUP BY 1),
grid AS (SELECT CAST(unnest(generate_series((SELECT min(d) FROM day), (SELECT max(d) FROM day), INTERVAL 1 DAY)) AS DATE) AS d),
filled AS (SELECT grid.d, coalesce(total, 0.0) AS total FROM grid LEFT JOIN day ON grid.d = day.d),
r AS (SELECT date_diff('day', (SELECT min(d) FROM day), d) AS i, sum(total - (SELECT avg(total) FROM filled)) OVER (ORDER BY d ROWS UNBOUNDED PRECEDING) AS running FROM filled)
SELECT i AS series_id, round(running, 0) AS last FROM r WHERE i >= 255""")
def daily_orders_series(t: Tables):
    return C.series(t, "daily256").select("series_id", F.round(F.get("values", F.lit(255)), 0).alias("last"))


# --- summaries ----------------------------------------------------------------------------------


@query("WITH " + ctes("walk64") + " SELECT series_id, round(list_sum(list_transform(z, lambda x: x * x)), 6) AS norm2, round(z[1], 6) AS first FROM z")
def znorm_stats(t: Tables):
    z = S.znorm(F.col("values"))
    return C.series(t, "walk64").withColumn("z", z).select("series_id", F.round(F.aggregate(F.transform("z", lambda x: x * x), F.lit(0.0), lambda a, x: a + x), 6).alias("norm2"), F.round(F.get("z", F.lit(0)), 6).alias("first"))


@query("WITH " + ctes("walk64") + " SELECT series_id, CAST(generate_subscripts(paa, 1) - 1 AS BIGINT) AS seg, unnest(paa) AS mean FROM p")
def paa8(t: Tables):
    return _summaries(t, "walk64").select("series_id", F.posexplode("paa").alias("seg", "mean")).select("series_id", F.col("seg").cast("bigint").alias("seg"), "mean")


_WORDS = "list_aggregate(list_transform(word, lambda x: CAST(x AS VARCHAR)), 'string_agg', ',') AS word"
for _name in ("walk64", "parts64", "signal256"):
    query("WITH " + ctes(_name) + f" SELECT series_id, {_WORDS}, CAST(bucket AS BIGINT) AS bucket FROM s", name=f"sax_words_{_name}")(
        lambda t, _name=_name: _summaries(t, _name).select("series_id", _word().alias("word"), F.col("bucket").cast("bigint").alias("bucket"))
    )


@query("WITH " + ctes("walk64") + f" SELECT series_id, {_WORDS}, CAST(bucket AS BIGINT) AS bucket FROM s")
def sax_words_by_expressions(t: Tables):
    paa = S.paa(S.znorm(F.col("values")), 64, 8)
    got = C.series(t, "walk64").withColumn("paa", paa).withColumn("word", S.word(F.col("paa"), 8))
    return got.select("series_id", _word().alias("word"), S.bucket(F.col("word"), 8).cast("bigint").alias("bucket"))


@query("WITH " + ctes("walk64") + f" SELECT series_id, {_WORDS} FROM s")
def sax_words_by_sql_functions(t: Tables):
    register(t.spark)
    C.series(t, "walk64").createOrReplaceTempView("_walks")
    return t.spark.sql("SELECT series_id, array_join(transform(sx_word(values, 8), x -> cast(x AS string)), ',') AS word FROM _walks")


@query("WITH " + ctes("parts64") + " SELECT CAST(bucket AS BIGINT) AS bucket, count(*) AS n FROM s GROUP BY bucket")
def bucket_occupancy(t: Tables):
    return X.bucket_stats(_summaries(t, "parts64")).select(F.col("bucket").cast("bigint").alias("bucket"), "n")


@query("WITH " + ctes("walk64") + " SELECT series_id, list_aggregate(list_transform(word, lambda x: CAST(x >> 4 AS VARCHAR)), 'string_agg', ',') AS word4 FROM s")
def coarsen_words(t: Tables):
    return _summaries(t, "walk64").select("series_id", _word(S.coarsen(F.col("word"), 8, 4)).alias("word4"))


_GAP = "sqrt({f} * list_sum(list_transform(range(1, 9), lambda j: pow(greatest({lo} - {a}, {b} - {hi}, 0.0), 2))))"
_ENDS = f"ends AS (SELECT list_concat([CAST('-inf' AS DOUBLE)], {_POINTS}, [CAST('inf' AS DOUBLE)]) AS e)"
_LB = _GAP.format(f="8.0", lo="e[b.word[j] + 1]", a="a.paa[j]", b="a.paa[j]", hi="e[b.word[j] + 2]")


@query(sql("walk64", f"SELECT query_id, series_id, round({_LB}, 6) AS lb FROM ask a, base b, ends").replace("cnt AS", _ENDS + ",\ncnt AS"))
def lb_matrix(t: Tables):
    base, ask = C.parted(t, "walk64")
    cfg = C.CONFIGS["walk64"]
    q = Q.Queries.of(ask, cfg)
    words = X.summarize(base, cfg)
    lo, hi = S.interval_ends(F.col("word"), 8)
    import numpy as np

    return Q.leaf_bounds(words.select("series_id", lo.alias("lo"), hi.alias("hi")), q, np.full(len(q.ids), np.inf), cfg, "series_id").select("query_id", "series_id", F.round("lb", 6).alias("lb"))


_LBW = _GAP.format(f="8.0", lo="e[b.word[j] + 1]", a="e[a.word[j] + 2]", b="e[a.word[j] + 1]", hi="e[b.word[j] + 2]")


def _word_bounds(base: DataFrame, ask: DataFrame) -> DataFrame:
    cfg = C.CONFIGS["walk64"]
    lo, hi = S.interval_ends(F.col("word"), 8)
    a = X.summarize(ask.withColumnRenamed("query_id", "series_id"), cfg).select(F.col("series_id").alias("query_id"), lo.alias("alo"), hi.alias("ahi"))
    b = X.summarize(base, cfg).select("series_id", lo.alias("blo"), hi.alias("bhi"))
    # the query set is 100 rows at any size
    return b.crossJoin(F.broadcast(a)).select("query_id", "series_id", F.round(S.lb_word_word(F.col("alo"), F.col("ahi"), F.col("blo"), F.col("bhi"), 64, 8), 6).alias("lb"))


@query(sql("walk64", f"SELECT query_id, series_id, round({_LBW}, 6) AS lb FROM ask a, base b, ends WHERE series_id < 40").replace("cnt AS", _ENDS + ",\ncnt AS"))
def lb_word_word(t: Tables):
    """The members that its SQL names; ``lb_word_word_matrix`` has all."""
    base, ask = C.parted(t, "walk64")
    return _word_bounds(base.where("series_id < 40"), ask)


@query(sql("walk64", f"SELECT query_id, series_id, round({_LBW}, 6) AS lb FROM ask a, base b, ends").replace("cnt AS", _ENDS + ",\ncnt AS"))
def lb_word_word_matrix(t: Tables):
    return _word_bounds(*C.parted(t, "walk64"))


def _bounds_and_distances(t: Tables) -> DataFrame:
    base, ask = C.parted(t, "walk64")
    lb = lb_matrix(t).withColumnRenamed("lb", "b")
    far = Q.brute_knn(base, ask, 1 << 30, C.CONFIGS["walk64"]).select("query_id", "series_id", "dist")
    return lb.join(far, ["query_id", "series_id"])


_LBD = f"SELECT {_LB} AS b, list_distance(a.z, b.z) AS dist FROM ask a, base b, ends"


@query(sql("walk64", f"SELECT count(*) AS pairs, round(avg(b / dist), 4) AS tightness, CAST(sum(CASE WHEN b > dist * (1 + 1e-9) THEN 1 ELSE 0 END) AS BIGINT) AS violations FROM ({_LBD})").replace("cnt AS", _ENDS + ",\ncnt AS"))
def tightness_summary(t: Tables):
    return _bounds_and_distances(t).agg(F.count(F.lit(1)).alias("pairs"), F.round(F.avg(F.col("b") / F.col("dist")), 4).alias("tightness"), F.sum((F.col("b") > F.col("dist") * (1 + 1e-6)).cast("bigint")).alias("violations"))


# --- trees --------------------------------------------------------------------------------------

for _name in ("walk64", "parts64"):
    query(sql(_name, "SELECT CAST(bucket AS BIGINT) AS bucket, path, n_items, CAST(inorder AS BIGINT) AS inorder, is_leaf FROM ranked", tree=True), name=f"tree_nodes_{_name}")(
        lambda t, _name=_name: C.index(t, _name).nodes.select(F.col("bucket").cast("bigint").alias("bucket"), "path", "n_items", "inorder", "is_leaf")
    )


@query(sql("parts64", "SELECT n_items, count(*) AS leaves FROM ranked WHERE is_leaf GROUP BY n_items", tree=True))
def leaf_histogram(t: Tables):
    return C.index(t, "parts64").nodes.where("is_leaf").groupBy("n_items").agg(F.count(F.lit(1)).alias("leaves"))


@query(sql("parts64", "SELECT CAST(p.bucket AS BIGINT) AS bucket, p.path, count(c.path) AS left_nodes FROM ranked p LEFT JOIN ranked c ON c.bucket = p.bucket AND starts_with(c.path, p.path || '0') GROUP BY ALL", tree=True))
def left_counts(t: Tables):
    return C.index(t, "parts64").nodes.select(F.col("bucket").cast("bigint").alias("bucket"), "path", "left_nodes")


@query(sql("parts64", "SELECT CAST(bucket AS BIGINT) AS bucket, count(*) AS total FROM ranked GROUP BY bucket", tree=True))
def rightmost_size(t: Tables):
    return X.tree_size(C.index(t, "parts64").nodes).select(F.col("bucket").cast("bigint").alias("bucket"), "total")


@query(sql("parts64", "SELECT CAST(bucket AS BIGINT) AS bucket, path, n_items FROM ranked WHERE inorder = 3", tree=True))
def node_at_3(t: Tables):
    return C.index(t, "parts64").nodes.where("inorder = 3").select(F.col("bucket").cast("bigint").alias("bucket"), "path", "n_items")


for _name in ("walk64", "parts64"):
    query(sql(_name, "SELECT count(DISTINCT bucket) AS roots, count(*) AS nodes, CAST(sum(is_leaf::INT) AS BIGINT) AS leaves, CAST(sum((is_leaf AND n_items = 0)::INT) AS BIGINT) AS empty_leaves, CAST(max(length(path)) AS BIGINT) AS max_depth, CAST(sum(CASE WHEN is_leaf THEN n_items ELSE 0 END) AS BIGINT) AS items FROM ranked", tree=True), name=f"tree_totals_{_name}")(
        lambda t, _name=_name: C.index(t, _name).stats().withColumn("max_depth", F.col("max_depth").cast("bigint"))
    )


@query()
def tree_balanced_totals(t: Tables):
    return C.index(t, "parts64", split_policy="balanced").stats()


# --- answers ------------------------------------------------------------------------------------

for _name, _k in (("walk64", 1), ("walk64", 5), ("parts64", 1), ("parts64", 10), ("signal256", 1)):
    _split = _SPLIT_WINDOWS if _name == "signal256" else _SPLIT
    query(sql(_name, _nearest(_k), split=_split), name=f"nn1_{_name}" if _k == 1 else f"knn{_k}_{_name}")(
        lambda t, _name=_name, _k=_k: _answers(Q.knn(C.index(t, _name), C.parted(t, _name)[1], _k))
    )
query(sql("vec64", _nearest(1), z=False), name="nn1_raw_vectors")(lambda t: _answers(Q.nn1(C.index(t, "vec64"), C.parted(t, "vec64")[1])))

_NN1 = {name: sql(name, _nearest(1)) for name in ("walk64", "parts64")}
for _strategy in B.STRATEGIES:
    query(_NN1["parts64"], name=f"nn1_parts64_{_strategy}")(lambda t, _strategy=_strategy: _answers(M.ask(G.Run(index=C.index(t, "parts64", _strategy)), C.parted(t, "parts64")[1], _strategy)))
for _mode in B.MODES:
    query(_NN1["walk64"], name=f"nn1_walk64_{_mode}_mode")(lambda t, _mode=_mode: _answers(Q.nn1(C.index(t, "walk64", mode=_mode), C.parted(t, "walk64")[1])))
for _stage in G.STAGES:
    for _name, _fault in (("delayed", P.Fault({0: 0.5})), ("dead", P.Fault(dead=frozenset([0])))):
        query(_NN1["parts64"], name=f"nn1_parts64_{_stage}_{_name}")(lambda t, _stage=_stage, _fault=_fault: _answers(_with_fault(t, "parts64", _stage, _fault)))


def _with_fault(t: Tables, name: str, stage: str, fault: P.Fault) -> DataFrame:
    """Nearest neighbours with a late or dead worker in one stage; the stages before it are taken from the plain index."""
    base, ask = C.parted(t, name)
    if stage in ("summarize", "tree"):
        return G.answer(base, ask, C.CONFIGS[name], faults={stage: fault}).answers
    return G.ask(G.Run(index=C.index(t, name)), ask, faults={stage: fault}).answers


@query(sql("walk64", "SELECT CAST(bucket AS BIGINT) AS bucket, path, n_items FROM ranked", tree=True))
def tree_nodes_by_inserts(t: Tables):
    """Two thirds are built at once, the rest is inserted in two batches."""
    base, cfg = C.parted(t, "walk64")[0], C.CONFIGS["walk64"]
    ix = X.build(base.where("series_id % 6 < 4"), cfg)
    for r in (4, 5):
        ix = X.insert_batch(ix, base.where(f"series_id % 6 = {r}"))
    return ix.nodes.select(F.col("bucket").cast("bigint").alias("bucket"), "path", "n_items")


@query(sql("walk64", """SELECT tree, CAST((SELECT count(*) FROM base) AS BIGINT) AS inserts, CAST(sum((NOT is_leaf)::INT) AS BIGINT) AS splits,
  CAST(sum((NOT is_leaf)::INT) + CASE WHEN tree = 'flagged' THEN 2 * (SELECT count(*) FROM base) ELSE 0 END AS BIGINT) AS flags
  FROM ranked, (VALUES ('flagged'), ('own')) v(tree) GROUP BY tree""", tree=True))
def insert_costs(t: Tables):
    """What taking series one by one costs: inserts, splits, and flags raised and lowered."""
    words = C.index(t, "walk64").summaries
    out = [B.trees_one_by_one(words, C.CONFIGS["walk64"], kind == "flagged").agg(*(F.sum(c).alias(c) for c in ("inserts", "splits", "flags"))).select(F.lit(kind).alias("tree"), "inserts", "splits", "flags") for kind in ("flagged", "own")]
    return out[0].unionByName(out[1])


@query(sql("walk64", """SELECT 'summarize' AS stage, CAST((SELECT count(*) FROM base) AS BIGINT) AS elements, CAST(0 AS BIGINT) AS undone
UNION ALL SELECT 'tree', CAST((SELECT count(*) FROM base) AS BIGINT), CAST(0 AS BIGINT)""", tree=False))
def helped_elements(t: Tables):
    """Series that the helped stages with a dead worker hand on, each once: by summaries, and by items of the tree's leaves."""
    run = G.build(C.parted(t, "walk64")[0], C.CONFIGS["walk64"], faults={s: P.Fault(dead=frozenset([0])) for s in ("summarize", "tree")})
    n = {"summarize": run.index.summaries.agg(F.count(F.lit(1)).alias("n")), "tree": run.index.nodes.where("is_leaf").agg(F.sum("n_items").alias("n"))}
    parts = [df.select(F.lit(s).alias("stage"), F.col("n").alias("elements"), F.lit(run.ledgers[s].where("not done").count()).cast("bigint").alias("undone")) for s, df in n.items()]
    return parts[0].unionByName(parts[1])


_VARIANTS = {
    "levelwise": lambda t: Q.nn1(C.index(t, "walk64"), C.parted(t, "walk64")[1], levelwise=True),
    "one_queue": lambda t: Q.nn1(C.index(t, "walk64", queues=1), C.parted(t, "walk64")[1]),
    "one_wave": lambda t: Q.nn1(C.index(t, "walk64", waves="one"), C.parted(t, "walk64")[1]),
    "seed_none": lambda t: Q.nn1(C.index(t, "walk64", seed_how="none"), C.parted(t, "walk64")[1]),
    "seed_best_lb": lambda t: Q.nn1(C.index(t, "walk64", seed_how="best_lb"), C.parted(t, "walk64")[1]),
    "balanced": lambda t: Q.nn1(C.index(t, "walk64", split_policy="balanced"), C.parted(t, "walk64")[1]),
    "single_queue": lambda t: G.single_queue(G.Run(index=C.index(t, "walk64")), C.parted(t, "walk64")[1]).answers,
    "flagged_tree": lambda t: Q.nn1(B.build(C.parted(t, "walk64")[0], C.CONFIGS["walk64"], "cas_claim", flagged=True), C.parted(t, "walk64")[1]),
    "incremental": lambda t: Q.nn1(X.insert_batch(X.build(C.parted(t, "walk64")[0].where("series_id % 2 = 0"), C.CONFIGS["walk64"]), C.parted(t, "walk64")[0].where("series_id % 2 = 1")), C.parted(t, "walk64")[1]),
    "scan": lambda t: Q.scan_knn(C.index(t, "walk64"), C.parted(t, "walk64")[1]),
    "brute": lambda t: Q.brute_knn(*C.parted(t, "walk64"), 1, C.CONFIGS["walk64"]),
}
for _name, _f in _VARIANTS.items():
    query(_NN1["walk64"], name=f"nn1_walk64_{_name}")(lambda t, _f=_f: _answers(_f(t)))


@query(sql("walk64", "SELECT query_id, series_id, round(list_distance(a.z, b.z), 6) AS dist FROM ask a, base b WHERE list_distance(a.z, b.z) <= 3.0"))
def range_walk64(t: Tables):
    return Q.range_search(C.index(t, "walk64"), C.parted(t, "walk64")[1], 3.0).select("query_id", "series_id", F.round("dist", 6).alias("dist"))


_BITS = f"list_aggregate(list_transform(range(0, {DEPTH}), lambda d: CAST((word[d % {W} + 1] >> (6 - d // {W})) & 1 AS VARCHAR)), 'string_agg', '')"
# symbols of a leaf have 1 bit of the bucket and those of the path, dealt round robin
_LEFT_OUT = "(7 - (length(l.path) + 8 - j) // 8)"
_LEAF_LB = _GAP.format(f="8.0", lo=f"e[((l.word[j] >> {_LEFT_OUT}) << {_LEFT_OUT}) + 1]", a="a.paa[j]", b="a.paa[j]", hi=f"e[(((l.word[j] >> {_LEFT_OUT}) + 1) << {_LEFT_OUT}) + 1]")


@query(sql("walk64", f""", place AS MATERIALIZED (
  SELECT b.series_id, b.z, b.word, n.bucket, n.path FROM (SELECT *, {_BITS} AS b FROM base) b JOIN ranked n ON n.bucket = b.bucket AND n.is_leaf AND n.path = b.b[1:length(n.path)]),
leaf AS MATERIALIZED (SELECT bucket, path, arg_min(word, series_id) AS word FROM place GROUP BY ALL),
asked AS (SELECT query_id, {_BITS} AS b, list_sum(list_transform(range(0, {W}), lambda j: (word[j + 1] >> 7) << ({W - 1} - j))) AS bucket FROM ask),
home AS MATERIALIZED (SELECT a.query_id, l.bucket, l.path FROM asked a JOIN leaf l ON l.bucket = a.bucket AND l.path = a.b[1:length(l.path)]),
far AS (SELECT query_id, bucket, path FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY lb, bucket, path) AS r FROM (
  SELECT a.query_id, l.bucket, l.path, {_LEAF_LB} AS lb FROM ask a, leaf l, ends WHERE a.query_id NOT IN (SELECT query_id FROM home))) WHERE r = 1)
SELECT query_id, series_id, round(dist, 6) AS dist FROM (
  SELECT a.query_id, p.series_id, list_distance(a.z, p.z) AS dist, row_number() OVER (PARTITION BY a.query_id ORDER BY list_distance(a.z, p.z), p.series_id) AS r
  FROM ask a JOIN (SELECT * FROM home UNION ALL SELECT * FROM far) h ON h.query_id = a.query_id JOIN place p ON p.bucket = h.bucket AND p.path = h.path) WHERE r = 1""", tree=True).replace("cnt AS", _ENDS + ",\ncnt AS", 1).replace("\n, place", ",\nplace"))
def approx_nn(t: Tables):
    """The best member of each query's own leaf, or of the leaf of least bound where there is none."""
    return Q.approx_nn(C.index(t, "walk64"), C.parted(t, "walk64")[1]).select("query_id", "series_id", F.round("dist", 6).alias("dist"))


@query(sql("walk64", "SELECT query_id, series_id, round(dist, 6) AS dist FROM (SELECT a.series_id AS query_id, b.series_id, list_distance(a.z, b.z) AS dist, row_number() OVER (PARTITION BY a.series_id ORDER BY list_distance(a.z, b.z), b.series_id) AS r FROM base a JOIN base b ON a.series_id <> b.series_id) WHERE r = 1"))
def self_nn(t: Tables):
    return Q.self_nn(C.index(t, "walk64")).select("query_id", "series_id", F.round("dist", 6).alias("dist"))


@query(sql("walk64", """SELECT query_id, CAST(count(*) AS BIGINT) AS alive FROM (
  SELECT a.query_id, b.series_id FROM ask a, base b, ends, (SELECT query_id AS q, min(list_distance(a.z, b.z)) AS nn FROM ask a, base b GROUP BY query_id) m
  WHERE m.q = a.query_id AND """ + _LB + " * (1 - 1e-9) <= nn) GROUP BY query_id").replace("cnt AS", _ENDS + ",\ncnt AS"))
def alive_items_final_bsf(t: Tables):
    """Members of each query whose own bound doesn't exceed the true nearest distance."""
    ix, ask = C.index(t, "walk64"), C.parted(t, "walk64")[1]
    q = Q.Queries.of(ask, ix.cfg)
    bsf = Q._kth(Q.knn(ix, ask, 1), q, 1)
    items = Q._item_bounds(ix, q, bsf, Q.prune(ix, q, bsf))
    return items.groupBy("query_id").agg(F.count(F.lit(1)).alias("alive"))


@query()
def noisy_nn(t: Tables):
    """Share of noisy members whose nearest member is the one they came from, by noise."""
    out = None
    ix = C.index(t, "walk64")
    base = C.parted(t, "walk64")[0]
    for sigma in (0.01, 0.02, 0.05, 0.1):
        got = Q.nn1(ix, src.noisy_queries(base, sigma, 100)).agg(F.lit(sigma).alias("sigma"), F.avg((F.col("query_id") == F.col("series_id")).cast("double")).alias("own"))
        out = got if out is None else out.unionByName(got)
    return out


# --- parts --------------------------------------------------------------------------------------


@query("SELECT CAST(event_id // sz AS BIGINT) AS chunk, CAST((event_id % sz) // gs AS BIGINT) AS grp, count(*) AS n FROM events, (SELECT sz, CAST(ceil(sz / 4.0) AS BIGINT) AS gs FROM (SELECT CAST(ceil((max(event_id) + 1) / 8.0) AS BIGINT) AS sz FROM events)) GROUP BY ALL")
def parts_layout(t: Tables):
    got = P.split_parts(t.events.select("event_id"), "event_id", 8, 4)
    return got.groupBy(F.col("chunk").cast("bigint").alias("chunk"), F.col("grp").cast("bigint").alias("grp")).agg(F.count(F.lit(1)).alias("n"))


def _helped(t: Tables) -> tuple[P.Stage, DataFrame, DataFrame]:
    base = C.parted(t, "walk64")[0]
    stage = P.Stage(t.spark, "summaries")
    cfg = C.CONFIGS["walk64"]
    part = F.pmod("series_id", F.lit(6))
    ledger = P.run_parts(stage, range(6), lambda p: X.summarize(base.where(part == p), cfg), owners=2, fault=P.Fault(delays={0: 2.0}), backoff_factor=0.5)
    return stage, ledger, base


@query(sql("walk64", "SELECT CAST(0 AS BIGINT) AS missing, count(*) AS seen, CAST(0 AS BIGINT) AS dups FROM base"))
def traversed_check(t: Tables):
    stage, _, base = _helped(t)
    return P.check_traversed(base, stage.read(), "series_id")


@query("SELECT CAST(unnest(range(0, 6)) AS BIGINT) AS part_id, true AS done")
def undone_parts(t: Tables):
    return _helped(t)[1].select("part_id", "done")


@query("WITH " + ctes("walk64") + f" SELECT series_id, {_WORDS} FROM s")
def traverse_groups(t: Tables):
    """Summaries by chunks and groups with one late worker."""
    stage, _ = P.traverse_collection(C.series(t, "walk64"), "series_id", 3, 2, lambda df: X.summarize(df, C.CONFIGS["walk64"]), fault=P.Fault({0: 1.0}))
    return stage.read().select("series_id", _word().alias("word"))


@query(sql("walk64", "SELECT count(*) AS rows FROM base"))
def helped_dedup(t: Tables):
    stage, _, _ = _helped(t)
    return P.dedup(stage.attempts(), "series_id").agg(F.count(F.lit(1)).alias("rows"))


@query()
def multiplicity_ratio(t: Tables):
    return P.multiplicity(_helped(t)[0].attempts(), "series_id")


@query("SELECT count(*) AS parts, CAST(0 AS BIGINT) AS overlap, round(max(n) / avg(n), 6) AS largest_over_mean FROM (SELECT l_partkey % 8 AS p, count(*) AS n FROM lineitem GROUP BY 1)")
def locality_report(t: Tables):
    got = P.locality_report(t.lineitem.select(F.pmod("l_partkey", F.lit(8)).alias("p"), "l_partkey"), "p", "l_partkey")
    return got.select("parts", "overlap", F.round("largest_over_mean", 6).alias("largest_over_mean"))


# --- simulator ----------------------------------------------------------------------------------


@query("SELECT CAST(d AS DOUBLE) AS delay, CAST(2 + d AS DOUBLE) AS makespan FROM (SELECT unnest(range(0, 11)) AS d)")
def sim_barrier_delay(t: Tables):
    return Z.scenarios(t.spark, [1.0] * 8, [dict(scenario="delay", policy="barrier", workers=4, delayed=1, delay=float(d)) for d in range(11)]).select("delay", "makespan")


@query("SELECT CAST(d AS DOUBLE) AS delay, CAST(CASE WHEN d = 0 THEN 2 ELSE 3 END AS DOUBLE) AS makespan FROM (SELECT unnest(range(0, 11)) AS d)")
def sim_helping_delay(t: Tables):
    return Z.scenarios(t.spark, [1.0] * 8, [dict(scenario="delay", policy="helping", workers=4, delayed=1, delay=float(d)) for d in range(11)]).select("delay", "makespan")


@query("SELECT CAST(p AS INTEGER) AS workers, CAST(ceil(48.0 / p) AS DOUBLE) AS makespan FROM (SELECT unnest([1, 2, 3, 4, 6, 8, 12, 24]) AS p)")
def sim_counter_claim(t: Tables):
    return Z.scenarios(t.spark, [1.0] * 48, [dict(scenario="workers", policy="counter_claim", workers=p) for p in (1, 2, 3, 4, 6, 8, 12, 24)]).select("workers", "makespan")


@query("SELECT CAST(f AS INTEGER) AS failed, CAST(NULL AS DOUBLE) AS makespan, false AS finished FROM (SELECT unnest(range(1, 8)) AS f)")
def sim_barrier_failure(t: Tables):
    return Z.scenarios(t.spark, [1.0] * 96, [dict(scenario="fail", policy="barrier", workers=8, failed=f) for f in range(1, 8)]).select("failed", "makespan", "finished")


@query("SELECT CAST(f AS INTEGER) AS failed, true AS finished, true AS close FROM (SELECT unnest(range(0, 8)) AS f)")
def sim_help_failure(t: Tables):
    """Makespan with f dead workers against that of the live ones alone."""
    cases = [dict(scenario="fail", policy="helping", workers=8, failed=f) for f in range(8)]
    alone = [dict(scenario="alone", policy="helping", workers=8 - f) for f in range(8)]
    got = Z.scenarios(t.spark, [1.0] * 96, cases).select("failed", "finished", "makespan")
    ref = Z.scenarios(t.spark, [1.0] * 96, alone).select((8 - F.col("workers")).alias("failed"), F.col("makespan").alias("ref"))
    return got.join(ref, "failed").select("failed", "finished", (F.abs(F.col("makespan") - F.col("ref")) <= 0.15 * F.col("ref") + 2).alias("close"))


@query()
def sim_all_policies(t: Tables):
    cases = [dict(scenario=s, policy=p, workers=w, delayed=d, delay=float(x), failed=f, levels=lv, backoff=b) for p in Z.POLICIES for s, w, d, x, f, lv, b in (("plain", 8, 0, 0, 0, 1, 0.0), ("late", 8, 1, 10, 0, 1, 0.0), ("late deep", 8, 1, 10, 0, 3, 0.5), ("many late", 8, 4, 5, 0, 1, 1.0), ("dead", 8, 0, 0, 2, 2, 0.0), ("oversubscribed", 24, 12, 5, 0, 1, 2.0))]
    return Z.scenarios(t.spark, [1.0 + (k * 7 % 5) / 4 for k in range(64)], cases)


@query()
def sim_tree_modes(t: Tables):
    rows = [(m, float(d), o.makespan, o.dups) for d in (0, 5, 20) for m, o in Z.tree_modes([1.0 + (k * 7 % 5) / 4 for k in range(40)], 8, {0: float(d)}).items()]
    return t.spark.createDataFrame(rows, "mode string, delay double, makespan double, dups bigint")


# --- sources and sinks --------------------------------------------------------------------------


def _round_trip(t: Tables, fmt: str, name: str, **options) -> DataFrame:
    path = f"{shared_folder(t.spark)}/round-trip-{uuid.uuid4()}"
    df = getattr(t, name)
    df.write.format(fmt).options(**options).save(path)
    return t.spark.read.format(fmt).schema(df.schema).options(**options).load(path)


@query("SELECT * FROM supplier")
def src_csv_round_trip(t: Tables):
    return _round_trip(t, "csv", "supplier", header=True)


@query("SELECT * FROM labels")
def src_jsonl_round_trip(t: Tables):
    return _round_trip(t, "json", "labels")


@query("SELECT * FROM part")
def src_orc_round_trip(t: Tables):
    return _round_trip(t, "orc", "part")


@query("SELECT n_name FROM nation")
def src_text_round_trip(t: Tables):
    path = f"{shared_folder(t.spark)}/round-trip-{uuid.uuid4()}"
    t.nation.select("n_name").write.text(f"{path}/nation.text")
    return src.load(t.spark, path, "nation", "text").withColumnRenamed("value", "n_name")


@query("SELECT row_number() OVER (ORDER BY vec_id) - 1 AS position, round(CAST(embedding[1] AS DOUBLE), 6) AS first, round(CAST(embedding[64] AS DOUBLE), 6) AS last FROM embeddings")
def src_f32_round_trip(t: Tables):
    path = f"{shared_folder(t.spark)}/f32-{uuid.uuid4()}"
    src.write_f32(C.series(t, "vec64"), path, 64)
    got = R.dense_index(src.read_f32(t.spark, path, 64), "file", "line", "row")
    return got.select(F.col("i").alias("position"), F.round(F.get("values", F.lit(0)), 6).alias("first"), F.round(F.get("values", F.lit(63)), 6).alias("last"))


@query(sql("walk64", _nearest(1)))
def src_index_save_load(t: Tables):
    from ..sources import store

    ix = C.index(t, "walk64")
    path = f"{shared_folder(t.spark)}/index-{uuid.uuid4()}"
    store.save(ix, path)
    return _answers(Q.nn1(store.load(t.spark, path), C.parted(t, "walk64")[1]))


@query(sql("walk64", _nearest(1)))
def src_index_append(t: Tables):
    from ..sources import store

    base, ask = C.parted(t, "walk64")
    path = f"{shared_folder(t.spark)}/index-{uuid.uuid4()}"
    store.save(B.build(base.where("series_id % 3 <> 0"), C.CONFIGS["walk64"], "level"), path)
    store.append(t.spark, path, base.where("series_id % 3 = 0"), batch_id=1)
    store.append(t.spark, path, base.where("series_id % 3 = 0"), batch_id=1)  # a replayed batch changes nothing
    return _answers(Q.nn1(store.load(t.spark, path), ask))


@query("SELECT 'null array' AS reason, count(*) AS n FROM embeddings WHERE vec_id % 5 = 0 UNION ALL SELECT 'wrong length', count(*) FROM embeddings WHERE vec_id % 5 = 1 UNION ALL SELECT 'non-finite point', count(*) FROM embeddings WHERE vec_id % 5 = 2")
def src_rejected_rows(t: Tables):
    s = C.series(t, "vec64")
    k = F.col("series_id") % 5
    bad = s.withColumn("values", F.when(k == 0, F.lit(None)).when(k == 1, F.slice("values", 1, 9)).when(k == 2, F.transform("values", lambda x: F.lit(float("nan")))).otherwise(F.col("values")))
    return src.validate_series(bad, 64)[1].groupBy("reason").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT CAST(unnest(range(0, 300)) AS BIGINT) AS series_id, true AS same")
def src_walk_generator(t: Tables):
    """Generated walks don't depend on how they are dealt to tasks."""
    a, b = (src.random_walks(t.spark, 300, 64, 7, p) for p in (2, 5))
    return a.join(b.withColumnRenamed("values", "other"), "series_id").select("series_id", (F.col("values") == F.col("other")).alias("same"))


@query("SELECT CAST(r AS BIGINT) AS rate, CAST(2 + 5 * r AS DOUBLE) AS makespan FROM (SELECT unnest(range(0, 6)) AS r)")
def sim_delay_rate(t: Tables):
    """Several delays a worker: the barrier pays each of them."""
    return t.spark.createDataFrame([(r, Z.simulate([1.0] * 8, "barrier", 4, Z.at_rate({0: 5.0}, r)).makespan) for r in range(6)], "rate bigint, makespan double")


@query("SELECT CAST(w AS BIGINT) AS workers, 12.0::DOUBLE AS makespan FROM (SELECT unnest([4, 8, 16]) AS w)")
def sim_oversubscribed(t: Tables):
    """More workers than cores take the same time, each at a share of a core."""
    return t.spark.createDataFrame([(w, Z.oversubscribed([1.0] * 48, "counter_claim", w, 4).makespan) for w in (4, 8, 16)], "workers bigint, makespan double")
