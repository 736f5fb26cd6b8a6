"""SimHash near-duplicates by anchor-point covering.

A fingerprint has 64 bits, one per bit of the XXH64 of the text's four-word shingles. To link
all pairs within four bits, the bits are cut into blocks of 23, 23 and 18; two linked
fingerprints differ in at most one bit of some block. The codewords of the perfect binary Golay
code of length 23 (18 bits are filled up with zeros) are the anchors of a block: every word lies
within three bits of exactly one anchor, its home, so its partner lies within four bits of the
same anchor. Each distinct fingerprint goes to all anchors within four bits (one or six of
4,096) and homes are compared with visitors per anchor; every candidate is checked over all 64
bits. Copies share a fingerprint and are collapsed before; each anchor hands on a spanning
forest, never all of its pairs.

Null or blank text has fingerprint zero and is linked like any other. Repeated rows give
repeated results; an empty table gives no rows; a null id has no part in links and gets a null
component. Other columns are ignored.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import apart, components, cut, map_batches

SHINGLE, SEED, RADIUS, THRESHOLD = 4, 42, 3, 4
#: First bit and width of the blocks.
BLOCKS = ((0, 23), (23, 23), (46, 18))
#: Fixed value: generator polynomial of the Golay code.
GENERATOR = 0b101011100011


def fingerprint(text: str | None) -> int:
    """Majority of the bits of the shingles' hashes, repeats included."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    ends, at = [], -1
    for w in words:
        at += len(w) + 1
        ends.append(at)
    if len(words) <= SHINGLE:
        hashes = [xxhash.xxh64_intdigest(joined, SEED)]
    else:
        digest = xxhash.xxh64_intdigest
        starts = [0, *(e + 1 for e in ends[: len(words) - SHINGLE])]
        hashes = [digest(joined[s:e], SEED) for s, e in zip(starts, ends[SHINGLE - 1 :], strict=True)]
    bits = np.unpackbits(np.array(hashes, dtype="<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    over = 2 * bits.sum(axis=0, dtype=np.int64) > len(hashes)
    return int(np.packbits(over, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long)."""

    def run():
        return lambda texts: [np.array([fingerprint(t) for t in texts], dtype=np.uint64).view(np.int64)]

    return map_batches(docs, ["doc_id"], ["text"], [T.StructField("fp", T.LongType())], run)


def _remainders(words: np.ndarray) -> np.ndarray:
    """Syndromes: remainders of 23-bit words by the generator."""
    x = words.astype(np.int64)
    for bit in range(22, 10, -1):
        x = np.where(x >> bit & 1 == 1, x ^ (GENERATOR << (bit - 11)), x)
    return x


def _patterns() -> np.ndarray:
    """For each syndrome the error patterns of weight four or less, home first, filled up with -1."""
    found: list[list[int]] = [[] for _ in range(2048)]
    for weight in range(THRESHOLD + 1):
        pats = np.array([sum(1 << i for i in c) for c in combinations(range(23), weight)], dtype=np.int64)
        for p, s in zip(pats.tolist(), _remainders(pats).tolist(), strict=True):
            found[s].append(p)
    most = max(map(len, found))
    return np.array([f + [-1] * (most - len(f)) for f in found], dtype=np.int64)


def anchors(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(key, index of the fingerprint, is home) for all anchors within covering radius plus threshold."""
    patterns = _patterns()
    keys, rows, homes = [], [], []
    for k, (start, width) in enumerate(BLOCKS):
        part = (fps.view(np.uint64) >> np.uint64(start)).astype(np.int64) & ((1 << width) - 1)
        errors = patterns[_remainders(part)]
        r, c = np.nonzero(errors >= 0)
        keys.append(((part[r] ^ errors[r, c]) << 2) | k)
        rows.append(r)
        homes.append(c == 0)
    return np.concatenate(keys), np.concatenate(rows), np.concatenate(homes)


def _links_at(home: np.ndarray, fps: np.ndarray, block: int = 512):
    """Index pairs within the threshold: home rows against all rows of an anchor, in blocks."""
    idx = np.flatnonzero(home)
    for at in range(0, len(idx), block):
        mine = idx[at : at + block]
        for lo in range(0, len(fps), 1 << 15):
            r, c = np.nonzero(np.bitwise_count(fps[mine, None] ^ fps[None, lo : lo + (1 << 15)]) <= THRESHOLD)
            keep = mine[r] != c + lo
            yield mine[r[keep]], c[keep] + lo


def _forest(fps: np.ndarray, home: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges from each fingerprint to the smallest one its anchor links it with."""
    root = np.arange(len(fps))
    for r, c in _links_at(home, fps):
        while True:  # smallest label over this block's links until none changes
            low = np.minimum(root[r], root[c])
            before = root.copy()
            np.minimum.at(root, r, low)
            np.minimum.at(root, c, low)
            np.minimum.at(root, before, root)
            root = root[root]
            if (root == before).all():
                break
    moved = np.flatnonzero(root != np.arange(len(fps)))
    return moved, root[moved]


def _compare(batches):
    """Rows come sorted by anchor; an anchor's rows are gathered across batches."""
    held: list[tuple[np.ndarray, ...]] = []

    def settle(parts):
        key, fp, home, rep = (np.concatenate(x) for x in zip(*parts, strict=True))
        cuts = np.flatnonzero(np.diff(key)) + 1
        a, b = [], []
        for lo, hi in zip([0, *cuts], [*cuts, len(key)], strict=True):
            if hi - lo > 1 and home[lo:hi].any():
                x, y = _forest(fp[lo:hi], home[lo:hi])
                a.append(rep[lo:hi][x])
                b.append(rep[lo:hi][y])
        a, b = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (a, b))
        pairs = np.unique(np.stack([a, b], axis=1), axis=0) if len(a) else np.zeros((0, 2), np.int64)
        return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(pairs[:, i])) for i in (0, 1)], names=["a", "b"])

    for batch in batches:
        key, fp, home, rep = batch.column(0).to_numpy(), batch.column(1).to_numpy().view(np.uint64), batch.column(2).to_numpy(zero_copy_only=False), batch.column(3).to_numpy()
        if not len(key):
            continue
        last = int(np.searchsorted(key, key[-1]))
        if last:
            yield settle([*held, (key[:last], fp[:last], home[:last], rep[:last])])
            held = []
        held.append((key[last:], fp[last:], home[last:], rep[last:]))
    if held:
        yield settle(held)


def links(distinct: DataFrame) -> DataFrame:
    """(a, b): a spanning forest of the links among distinct fingerprints ``fp``, each named by its document ``rep``."""

    def spread(batches):
        for b in batches:
            fps, reps = b.column(0).to_numpy(), b.column(1).to_numpy()
            key, row, home = anchors(fps)
            for at in range(0, len(key), 1 << 16):
                s = slice(at, at + (1 << 16))
                yield pa.RecordBatch.from_arrays([pa.array(key[s].astype(np.int32)), pa.array(fps[row[s]]), pa.array(home[s]), pa.array(reps[row[s]])], names=["anchor", "fp", "home", "rep"])

    rows = distinct.select("fp", F.col("rep").cast("bigint").alias("rep")).mapInArrow(spread, "anchor int, fp bigint, home boolean, rep bigint")
    return rows.repartition("anchor").sortWithinPartitions("anchor", "fp").mapInArrow(_compare, "a bigint, b bigint").distinct()


def groups(docs: DataFrame) -> DataFrame:
    """doc_id, fp, component_id for every row of ``docs``."""
    fps = cut(fingerprints(docs))
    reps = cut(fps.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("rep")))
    # each fingerprint goes by its smallest document, so the smallest of a component is the component's name
    roots = components(links(reps))
    final = reps.join(roots, F.col("rep") == F.col("node"), "left").select(F.col("fp").alias("fp_"), F.coalesce("root", "rep").alias("least_"))
    joined = fps.join(final, F.col("fp") == F.col("fp_"), "left")
    return joined.select("doc_id", "fp", F.when(F.col("doc_id").isNotNull(), F.col("least_")).alias("component_id"))


def one_of_each(docs: DataFrame) -> DataFrame:
    """``docs`` with the smallest document of each group only; all columns stay. Rows of a null id stay,
    of rows with an equal id one stays."""
    docs, back = apart(docs)
    kept = groups(docs).where("doc_id = component_id").select("doc_id").distinct()
    named = docs.where("doc_id is not null").join(kept, "doc_id", "left_semi").dropDuplicates(["doc_id"])
    return back(named.unionByName(docs.where("doc_id is null")))


def hex_digits(fp: str = "fp"):
    return F.lower(F.lpad(F.hex(F.col(fp)), 16, "0"))
