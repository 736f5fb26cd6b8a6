"""The stand-in collections by name, and their indexes, built once a query."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame

from ..config import IndexConfig
from ..operators import baselines as B
from ..operators import series as R
from ..operators.index import SeriesIndex
from ..session import cut
from .registry import Tables

BASE = IndexConfig()
CONFIGS = {
    "walk64": BASE,
    "parts64": BASE,
    "vec64": replace(BASE, normalise="none"),
    "signal256": replace(BASE, n=256),
    "user32": replace(BASE, n=32),
    "daily256": replace(BASE, n=256),
}


def _once(t: Tables, key: tuple, make):
    if key not in t.kept:
        t.kept[key] = make()
    return t.kept[key]


def series(t: Tables, name: str) -> DataFrame:
    """(series_id, values) of a collection, whole."""

    def make():
        if name == "signal256":
            return raw(t, name).frame
        kinds = {"walk64": lambda: R.walk64(t.embeddings), "vec64": lambda: R.vec64(t.embeddings), "parts64": lambda: R.parts64(t.lineitem), "user32": lambda: R.user32(t.events), "daily256": lambda: R.daily256(t.orders)}
        return cut(kinds[name]())

    return _once(t, ("series", name), make)


def raw(t: Tables, name: str) -> R.Raw:
    """A collection held once, for steps that leave its values where they are: windows by their points."""
    return _once(t, ("raw", name), lambda: R.signal256_blocks(t.events) if name == "signal256" else R.plain(series(t, name)))


def parted(t: Tables, name: str) -> tuple[DataFrame, DataFrame]:
    """(collection, 100 outside queries). Windows that overlap a query leave the collection with it."""

    def make():
        every = series(t, name)
        if name in ("signal256", "daily256"):
            top = every.agg({"series_id": "max"}).first()[0]
            n = CONFIGS[name].n
            ask = every.where(f"series_id > {top - 100}").withColumnRenamed("series_id", "query_id")
            return every.where(f"series_id <= {top - 100 - (n - 1)}"), ask
        return R.split_outside(every, every.count())

    return _once(t, ("parted", name), make)


def members(t: Tables, name: str) -> R.Raw:
    """As :func:`raw`, without the queries."""
    return replace(raw(t, name), frame=parted(t, name)[0])


def index(t: Tables, name: str, strategy: str = "level", mode: str | None = None, **changes) -> SeriesIndex:
    """An index over the collection without the queries. "level": the plain set-at-a-time build."""
    cfg = replace(CONFIGS[name], **changes)

    def make():
        base = parted(t, name)[0]
        return B.build(base, cfg, strategy, mode, raw=members(t, name) if name == "signal256" else None)

    return _once(t, ("index", name, strategy, mode, cfg), make)
