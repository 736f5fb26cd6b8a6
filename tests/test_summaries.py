"""Kernels against worked examples and their Column twins; the bound law."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from serieslake.config import IndexConfig
from serieslake.functions import summaries as S
from serieslake.functions.registry import register
from serieslake.operators import index as X

A, B, Q = [1, 2, 4, 5, 7, 9, 6, 6], [9, 8, 6, 5, 3, 2, 1, 2], [1, 1, 3, 6, 8, 8, 7, 6]


def rows(*series):
    return S.znorm_rows(np.array(series, dtype=float))


def test_worked_example():
    z = rows(A, B, Q)
    paa = S.paa_rows(z, 4)
    assert np.allclose(paa[0], [-1.428869, -0.204124, 1.224745, 0.408248], atol=1e-6)
    assert np.allclose(paa[1], [1.436842, 0.359211, -0.718421, -1.077632], atol=1e-6)
    words = S.symbol_rows(paa, 2)
    assert words.tolist() == [[0, 1, 3, 2], [3, 2, 0, 0], [0, 1, 3, 2]]
    assert S.bucket_rows(words, 2).tolist() == [3, 12, 3]
    lo, hi = S.intervals(words, np.full((3, 4), 2), 2)
    lb = S.gap_rows(paa[2:], lo, hi, 8)[0]
    assert np.allclose(lb[:2], [0, 4.293806], atol=1e-6)
    assert np.allclose(S.distances(z[:2], z[[2, 2]]), [0.891481, 5.539901], atol=1e-6)


def test_breakpoints_nest_and_centre():
    for bits in range(1, 8):
        assert S.breakpoints(bits) == S.breakpoints(bits + 1)[1::2]
    assert S.symbol_rows(np.zeros((1, 1)), 8)[0, 0] == 128  # a mean on a breakpoint belongs to the upper half
    assert S.symbol_rows(S.paa_rows(rows([3.0] * 8), 4), 8).tolist() == [[128] * 4]


def test_uneven_segments_keep_the_mean():
    x = np.random.default_rng(0).standard_normal((5, 10))
    assert np.allclose(S.paa_rows(x, 4).mean(axis=1), x.mean(axis=1))
    assert np.allclose(S.frame_weights(10, 4).sum(axis=0), 1)


def test_early_abandon_gives_up_only_beyond_the_limit():
    rng = np.random.default_rng(1)
    x, q = rng.standard_normal((200, 64)), rng.standard_normal((200, 64))
    d = S.distances(x, q)
    got = S.distances(x, q, np.full(200, np.median(d)))
    assert np.array_equal(np.isfinite(got), d <= np.median(d))
    assert np.allclose(got[np.isfinite(got)], d[np.isfinite(got)])


@pytest.mark.parametrize("w", [4, 8, 16])
def test_bounds_never_exceed_distances(w):
    rng = np.random.default_rng(w)
    z = S.znorm_rows(np.cumsum(rng.standard_normal((150, 64)), axis=1))
    paa = S.paa_rows(z, w)
    word = S.symbol_rows(paa, 8)
    lo, hi = S.intervals(word, np.full_like(word, 8), 8)
    coarse_lo, coarse_hi = S.intervals(word >> 5, np.full_like(word, 3), 8)
    fine, coarse = S.gap_rows(paa, lo, hi, 64), S.gap_rows(paa, coarse_lo, coarse_hi, 64)
    dist = np.sqrt(((z[:, None] - z[None]) ** 2).sum(axis=2))
    assert (coarse <= fine + 1e-9).all() and (fine <= dist * (1 + 1e-9) + 1e-6).all()


def test_columns_equal_kernels(spark):
    rng = np.random.default_rng(2)
    x = np.cumsum(rng.standard_normal((20, 64)), axis=1)
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "series_id bigint, values array<double>")
    kernel = {r.series_id: r for r in X.summarize(df, IndexConfig()).collect()}
    cols = df.withColumn("paa", S.paa(S.znorm(F.col("values")), 64, 8)).withColumn("word", S.word(F.col("paa"), 8)).withColumn("bucket", S.bucket(F.col("word"), 8)).withColumn("first", S.symbol(F.get("paa", F.lit(0)), 8)).withColumn("hex", S.word_hex(F.col("word")))
    for r in cols.collect():
        k = kernel[r.series_id]
        assert (r.word, r.bucket, r["first"]) == (k.word, k.bucket, k.word[0])
        assert np.allclose(r.paa, k.paa) and r.hex == bytes(k.word).hex()
    covered = cols.select(S.covers(S.coarsen(F.col("word"), 8, 3), F.array_repeat(F.lit(3), 8), F.col("word"), 8).alias("c")).collect()
    assert all(r.c for r in covered)


def test_sql_functions(spark):
    register(spark)
    a, b = (", ".join(f"{float(v)}D" for v in s) for s in (A, Q))
    r = spark.sql(f"SELECT sx_dist(sx_znorm(array({a})), sx_znorm(array({b}))) AS d, sx_bucket(sx_word(array({a}), 4)) AS b, sx_word_hex(sx_word(array({a}), 4)) AS h, sx_lb(sx_paa(sx_znorm(array({b})), 4), sx_word(array({a}), 4), 8) AS lb, sx_covers(array(0), array(1), array(17)) AS c").first()
    assert abs(r.d - 0.891481) < 1e-6 and r.b == 3 and len(r.h) == 8 and 0 <= r.lb <= r.d and r.c
