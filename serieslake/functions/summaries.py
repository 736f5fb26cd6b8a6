"""Summaries of series and their lower bounds: numpy kernels for bulk work and Column twins for SQL users.

A series is z-normalised with the population deviation (all zeros where that is under 1e-8), cut into
w segments whose means (rounded to nine decimals, so that engines agree) become symbols by
N(0,1) quantiles. A symbol of fewer bits is a symbol of more bits shifted right.
"""

from __future__ import annotations

from functools import lru_cache
from statistics import NormalDist

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

FLAT, DECIMALS = 1e-8, 9


@lru_cache
def breakpoints(bits: int) -> tuple[float, ...]:
    """The 2**bits - 1 quantiles that cut N(0,1) into equal parts; each coarser set is part of each finer one."""
    size = 1 << bits
    return tuple(0.0 if 2 * i == size else NormalDist().inv_cdf(i / size) for i in range(1, size))


# --- numpy kernels: rows are series -------------------------------------------------------------


def znorm_rows(x: np.ndarray) -> np.ndarray:
    mean, dev = x.mean(axis=1, keepdims=True), x.std(axis=1, keepdims=True)
    return np.where(dev < FLAT, 0.0, (x - mean) / np.where(dev < FLAT, 1.0, dev))


@lru_cache
def frame_weights(n: int, w: int) -> np.ndarray:
    """(n, w) shares of each point in each segment; fractional where w doesn't divide n."""
    edges = np.arange(w + 1) * n / w
    lo = np.maximum(np.arange(n)[:, None], edges[None, :-1])
    hi = np.minimum(np.arange(1, n + 1)[:, None], edges[None, 1:])
    return np.clip(hi - lo, 0, None) * w / n


def paa_rows(x: np.ndarray, w: int) -> np.ndarray:
    n = x.shape[1]
    got = x.reshape(len(x), w, n // w).mean(axis=2) if n % w == 0 else x @ frame_weights(n, w)
    return np.round(got, DECIMALS)


def symbol_rows(paa: np.ndarray, bits: int) -> np.ndarray:
    return np.searchsorted(np.array(breakpoints(bits)), paa, side="right").astype(np.int32)


def bucket_rows(words: np.ndarray, bits: int) -> np.ndarray:
    """First bit of each symbol, packed; the first segment is the highest bit."""
    w = words.shape[1]
    return ((words >> (bits - 1)) << np.arange(w - 1, -1, -1)).sum(axis=1)


def intervals(symbols: np.ndarray, used: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Lower and upper ends of the value ranges of symbols of ``used`` bits."""
    points = np.array([-np.inf, *breakpoints(bits), np.inf])
    shift = bits - used
    return points[symbols << shift], points[(symbols + 1) << shift]


def gap_rows(paa: np.ndarray, lo: np.ndarray, hi: np.ndarray, n: int) -> np.ndarray:
    """Lower bounds (queries, nodes) between query means and value ranges."""
    w = paa.shape[1]
    total = np.zeros((len(paa), len(lo)))
    for j in range(w):
        g = np.maximum(np.maximum(lo[None, :, j] - paa[:, j, None], paa[:, j, None] - hi[None, :, j]), 0.0)
        total += g * g
    return np.sqrt(n / w * total)


def distances(x: np.ndarray, q: np.ndarray, bsf: np.ndarray | None = None, step: int = 16) -> np.ndarray:
    """True distances of paired rows. With ``bsf`` a pair is given up (infinite) once its partial sum passes it."""
    if bsf is None:
        d = x - q
        return np.sqrt(np.einsum("ij,ij->i", d, d))
    total, live = np.zeros(len(x)), np.arange(len(x))
    limit = bsf * bsf * (1 + 1e-9)
    for at in range(0, x.shape[1], step):
        d = x[live, at : at + step] - q[live, at : at + step]
        total[live] += np.einsum("ij,ij->i", d, d)
        over = total[live] > limit[live]
        if over.any():
            total[live[over]] = np.inf
            live = live[~over]
    return np.sqrt(total)


def block_filter(x: np.ndarray, q: np.ndarray, bsf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, query) pairs whose distance by matrix product may be within ``bsf``; never the answer itself."""
    d2 = (x * x).sum(axis=1)[:, None] - 2 * x @ q.T + (q * q).sum(axis=1)[None]
    return np.nonzero(d2 <= (bsf * bsf)[None] * (1 + 1e-6) + 1e-6)


# --- Column twins -------------------------------------------------------------------------------


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda a, x: a + x)


def _bind(value: Column, body) -> Column:
    """``body(value)`` with ``value`` computed once a row: what a lambda names from outside is computed for each element."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def znorm(values: Column) -> Column:
    def scaled(v: Column, mean: Column) -> Column:
        dev = F.sqrt(_sum(F.transform(v, lambda x: (x - mean) * (x - mean))) / F.size(v).cast("double"))
        return _bind(dev, lambda d: F.transform(v, lambda x: F.when(d < FLAT, F.lit(0.0)).otherwise((x - mean) / d)))

    return _bind(values, lambda v: _bind(_sum(v) / F.size(v).cast("double"), lambda mean: scaled(v, mean)))


def paa(values: Column, n: int, w: int) -> Column:
    """Segment means; ``w`` must divide ``n`` (the kernel has no such limit)."""
    size = n // w
    return _bind(values, lambda v: F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda j: F.round(_sum(F.slice(v, j * size + 1, F.lit(size))) / size, DECIMALS)))


def symbol(value: Column, bits: int) -> Column:
    """Count of breakpoints at or below ``value``, by binary search."""
    points = F.array(*map(F.lit, breakpoints(bits)))
    got = F.lit(0)
    for b in range(bits - 1, -1, -1):
        probe = got + (1 << b)
        got = F.when(F.get(points, probe - 1) <= value, probe).otherwise(got)
    return got.cast("int")


def word(paa_: Column, bits: int) -> Column:
    return F.transform(paa_, lambda x: F.size(F.filter(F.array(*map(F.lit, breakpoints(bits))), lambda p: p <= x)).cast("int"))


def bucket(word_: Column, bits: int) -> Column:
    return F.aggregate(word_, F.lit(0), lambda a, s: F.shiftleft(a, 1) + F.shiftright(s, bits - 1))


def coarsen(word_: Column, bits: int, to: int) -> Column:
    return F.transform(word_, lambda s: F.shiftright(s, bits - to))


def covers(syms: Column, used: Column, word_: Column, bits: int) -> Column:
    """Whether a node's symbols of ``used`` bits are prefixes of a word's."""
    return F.forall(F.arrays_zip(syms.alias("s"), used.alias("u"), word_.alias("x")), lambda z: z["s"] == F.call_function("shiftright", z["x"], F.lit(bits) - z["u"]))


def interval_ends(word_: Column, bits: int) -> tuple[Column, Column]:
    points = F.array(F.lit(float("-inf")), *map(F.lit, breakpoints(bits)), F.lit(float("inf")))
    return F.transform(word_, lambda s: F.get(points, s)), F.transform(word_, lambda s: F.get(points, s + 1))


def lb_paa_word(q_paa: Column, lo: Column, hi: Column, n: int, w: int) -> Column:
    gaps = F.zip_with(q_paa, F.arrays_zip(lo.alias("lo"), hi.alias("hi")), lambda q, r: F.greatest(r["lo"] - q, q - r["hi"], F.lit(0.0)))
    return F.sqrt(F.lit(n / w) * _sum(F.transform(gaps, lambda g: g * g)))


def lb_word_word(a_lo: Column, a_hi: Column, b_lo: Column, b_hi: Column, n: int, w: int) -> Column:
    gaps = F.zip_with(F.arrays_zip(a_lo.alias("lo"), a_hi.alias("hi")), F.arrays_zip(b_lo.alias("lo"), b_hi.alias("hi")), lambda x, y: F.greatest(x["lo"] - y["hi"], y["lo"] - x["hi"], F.lit(0.0)))
    return F.sqrt(F.lit(n / w) * _sum(F.transform(gaps, lambda g: g * g)))


def dist(x: Column, y: Column) -> Column:
    return F.sqrt(_sum(F.zip_with(x, y, lambda a, b: (a - b) * (a - b))))


def word_hex(word_: Column) -> Column:
    return F.array_join(F.transform(word_, lambda s: F.lpad(F.lower(F.hex(s)), 2, "0")), "")
