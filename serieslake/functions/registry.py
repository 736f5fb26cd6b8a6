"""The kernels as SQL functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import summaries as S


def _rows(s: pd.Series) -> np.ndarray:
    return np.stack(s.to_numpy()).astype(np.float64) if len(s) else np.zeros((0, 1))


def register(spark: SparkSession) -> list[str]:
    """Registers sx_znorm, sx_paa, sx_word, sx_bucket, sx_lb, sx_dist, sx_word_hex and sx_covers; all Arrow-batched."""

    @F.pandas_udf(T.ArrayType(T.DoubleType()))
    def sx_znorm(v: pd.Series) -> pd.Series:
        return pd.Series(list(S.znorm_rows(_rows(v))), dtype=object)

    @F.pandas_udf(T.ArrayType(T.DoubleType()))
    def sx_paa(v: pd.Series, w: pd.Series) -> pd.Series:
        return pd.Series(list(S.paa_rows(_rows(v), int(w.iloc[0]))) if len(v) else [], dtype=object)

    @F.pandas_udf(T.ArrayType(T.IntegerType()))
    def sx_word(v: pd.Series, w: pd.Series) -> pd.Series:
        return pd.Series(list(S.symbol_rows(S.paa_rows(S.znorm_rows(_rows(v)), int(w.iloc[0])), 8)) if len(v) else [], dtype=object)

    @F.pandas_udf(T.IntegerType())
    def sx_bucket(word: pd.Series) -> pd.Series:
        return pd.Series(S.bucket_rows(np.stack(word.to_numpy()), 8) if len(word) else [], dtype="int32")

    @F.pandas_udf(T.DoubleType())
    def sx_dist(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series(S.distances(_rows(a), _rows(b)) if len(a) else [], dtype="float64")

    @F.pandas_udf(T.DoubleType())
    def sx_lb(paa: pd.Series, word: pd.Series, n: pd.Series) -> pd.Series:
        if not len(paa):
            return pd.Series([], dtype="float64")
        q, w = _rows(paa), np.stack(word.to_numpy())
        lo, hi = S.intervals(w, np.full_like(w, 8), 8)
        g = np.maximum(np.maximum(lo - q, q - hi), 0)
        return pd.Series(np.sqrt(n.iloc[0] / q.shape[1] * (g * g).sum(axis=1)))

    @F.pandas_udf(T.StringType())
    def sx_word_hex(word: pd.Series) -> pd.Series:
        return pd.Series(["".join(f"{x:02x}" for x in w) for w in word], dtype=object)

    @F.pandas_udf(T.BooleanType())
    def sx_covers(syms: pd.Series, used: pd.Series, word: pd.Series) -> pd.Series:
        return pd.Series([bool(((np.asarray(x) >> (8 - np.asarray(u))) == np.asarray(s)).all()) for s, u, x in zip(syms, used, word, strict=True)], dtype=bool)

    functions = dict(sx_znorm=sx_znorm, sx_paa=sx_paa, sx_word=sx_word, sx_bucket=sx_bucket, sx_lb=sx_lb, sx_dist=sx_dist, sx_word_hex=sx_word_hex, sx_covers=sx_covers)
    for name, f in functions.items():
        spark.udf.register(name, f)
    return list(functions)
