"""Benchmark decontamination by random-walk embedding and bit-sampling.

Edit distance is mapped to Hamming distance: a walk over a text writes at each step the sign it
stands on and then, by a random function of step and sign that all texts share, moves on or stays.
A walk that lost step by an edit rarely finds it again, so the walk over an item-sized window is
begun anew at each word: the window's embedding is made of short walks, one from each of its
starts. A band is a sample of the signs of one short walk; its hash is looked up among the bands of
all items, for ``REPEATS`` independent walks. Two bands from different starts that an item and a
document share at about the same offset make an item-sized window a candidate; its edit distance is
then computed exactly by bit vectors. No word or string has to agree as a whole.

A match is an edit distance of at most ``DISTANCE`` times the item's length, both as lower-case
words without punctuation. Recall is measured end to end, not derived: tests plant passages with
substituted, inserted and deleted letters at up to the bound and with a letter changed in every second word.

Items shorter than ``LONG`` bytes are sought by walks of few steps from every byte, a single band
being enough; items under ``TINY`` bytes by their exact edit distance to every text. Long words are
entered at content-chosen bytes too, so scripts without spaces are searched. Items without a letter or
digit match nothing. Null and empty texts match nothing; items of a null id take no part. Repeated
rows give repeated results; empty tables give no rows; other columns are ignored. Items are read and
broadcast in blocks of bounded size, one at a time on the driver, so the benchmark may grow.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

DISTANCE = 0.2
#: Independent walks; their number comes from the measured recall at the distance bound.
REPEATS = 6
LONG, TINY = 64, 10
#: Chars of the items broadcast at once, and bytes of texts walked at once.
BLOCK_CHARS, GROUP_BYTES = 16_000_000, 4 << 20
#: Words longer than this are entered inside, too.
LONG_WORD = 24
SPACES = bytes(c if c >= 128 or chr(c).isalnum() else 32 for c in range(256))
#: Signs fall into 32 classes, one for the space and one for each letter; other bytes share the rest.
CLASS = np.array([0 if c <= 32 else c - 96 if 97 <= c <= 122 else 27 + c % 5 for c in range(256)], dtype=np.uint16)


def normal(text: str | None) -> bytes:
    """Lower-case words without punctuation, one space between them."""
    return b" ".join((text or "").lower().encode("utf-8", "surrogatepass").translate(SPACES).split())


@dataclass(frozen=True)
class Profile:
    """Short walks of ``steps`` (a multiple of 3), of whose signs ``sampled`` make a band."""

    steps: int
    sampled: int
    repeats: int
    every_byte: bool
    need: int


PROFILES = (Profile(30, 14, REPEATS, False, 2), Profile(6, 6, 2, True, 1))


@lru_cache
def steps_of(profile: Profile, repeat: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each three steps: how far they move and what they add to the band's hash, by the next three signs."""
    rng = np.random.default_rng(1000 * profile.steps + repeat)
    moves = rng.integers(0, 2, size=(profile.steps, 32))
    values = rng.integers(0, 1 << 32, size=(profile.steps, 32), dtype=np.uint32)
    values[np.setdiff1d(np.arange(profile.steps), rng.choice(profile.steps, profile.sampled, replace=False))] = 0
    code = np.arange(1 << 15)
    signs = np.stack([code & 31, code >> 5 & 31, code >> 10])
    out = []
    for s in range(0, profile.steps, 3):
        at, adds = np.zeros(1 << 15, dtype=np.int64), np.zeros(1 << 15, dtype=np.uint32)
        for k in range(s, s + 3):
            sign = signs[at, code]
            adds ^= values[k, sign]
            at += moves[k, sign]
        out.append((at.astype(np.int32), adds))
    return out


def walk(codes: np.ndarray, starts: np.ndarray, profile: Profile, repeat: int) -> tuple[np.ndarray, np.ndarray]:
    """(band, place after the walk) for each start. ``codes`` holds the next three signs at each byte."""
    bands, ends = np.empty(len(starts), dtype=np.uint32), np.empty(len(starts), dtype=np.int32)
    tables = steps_of(profile, repeat)
    for lo in range(0, len(starts), 1 << 14):
        at = starts[lo : lo + (1 << 14)].astype(np.int32)
        h = bands[lo : lo + (1 << 14)]
        h[:] = 0
        for moves, adds in tables:
            code = codes.take(at, mode="clip")
            h ^= adds.take(code)
            at += moves.take(code)
        ends[lo : lo + (1 << 14)] = at
    return bands, ends


def coded(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, codes) of texts that are joined by a zero byte."""
    t = np.frombuffer(data, dtype=np.uint8)
    c = np.concatenate([CLASS[t], np.zeros(2, np.uint16)])
    return t, c[:-2] | c[1:-1] << 5 | c[2:] << 10


def word_starts(t: np.ndarray) -> np.ndarray:
    gap = t <= 32
    start = ~gap
    start[1:] &= gap[:-1]
    at = np.flatnonzero(start)
    if len(at):
        ends = np.flatnonzero(np.concatenate([gap[1:], [True]]) & ~gap) + 1
        for lo, hi in zip(at[ends - at > LONG_WORD].tolist(), ends[ends - at > LONG_WORD].tolist(), strict=True):
            inner = t[lo:hi].astype(np.uint32)
            start[lo + 1 : hi] = (inner[:-1] * 31 + inner[1:] * 17) % 5 == 0
        at = np.flatnonzero(start)
    return at


def within(item: bytes, text: bytes, most: int) -> tuple[int, int] | None:
    """(edit distance, end in text) of the best match of ``item`` with a part of ``text``, or None above ``most``."""
    n = len(text)
    t = np.frombuffer(text, dtype=np.uint8)
    row = np.zeros(n + 1, dtype=np.int32)
    ramp = np.arange(n + 1, dtype=np.int32)
    for i, c in enumerate(item, 1):
        best = np.empty(n + 1, dtype=np.int32)
        best[0] = i
        np.minimum(row[:-1] + (t != c), row[1:] + 1, out=best[1:])
        row = np.minimum.accumulate(best - ramp) + ramp
        if row.min() > most:
            return None
    end = int(row.argmin())
    return (int(row[end]), end) if row[end] <= most else None


def distances(masks: np.ndarray, sizes: np.ndarray, which: np.ndarray, texts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(edit distance, end) of the best match of item ``which`` in each row of ``texts``, by bit vectors of 64 rows.
    ``masks``: (items, 256, words) bits of the places where an item has a byte."""
    words = masks.shape[2]
    top = ((sizes[which] - 1) & 63).astype(np.uint64)
    one, all_ones = np.uint64(1), np.uint64(0xFFFFFFFFFFFFFFFF)
    up, down = [np.full(len(which), all_ones) for _ in range(words)], [np.zeros(len(which), np.uint64) for _ in range(words)]
    score = sizes[which].astype(np.int32)
    best, end = score.copy(), np.zeros(len(which), dtype=np.int32)
    for j in range(texts.shape[1]):
        row = masks[which, texts[:, j]]
        plus = minus = np.zeros(len(which), np.uint64)
        for w in range(words):
            eq, p, m = row[:, w], up[w], down[w]
            xv = eq | m
            eq = eq | minus
            xh = (((eq & p) + p) ^ p) | eq
            ph, mh = m | ~(xh | p), p & xh
            last = w == words - 1
            shift = top if last else np.uint64(63)
            out_plus, out_minus = ph >> shift & one, mh >> shift & one
            ph, mh = ph << one | plus, mh << one | minus
            up[w], down[w] = mh | ~(xv | ph), ph & xv
            plus, minus = out_plus, out_minus
        score += plus.astype(np.int32) - minus.astype(np.int32)
        better = score < best
        best[better], end[better] = score[better], j + 1
    return best, end


class Bands:
    """All bands of the items of a profile, sorted, with a table of bits before the search."""

    def __init__(self, texts: list[bytes], items: np.ndarray, profile: Profile):
        self.profile = profile
        t, codes = coded(b"\0".join(texts) + b"\0")
        sizes = np.array([len(x) for x in texts], dtype=np.int64)
        begin = np.cumsum(sizes + 1) - sizes - 1
        starts = np.flatnonzero(t > 0) if profile.every_byte else word_starts(t)
        own = np.searchsorted(begin, starts, side="right") - 1
        self.tables, valid = [], np.zeros(len(texts), dtype=np.int64)
        for r in range(profile.repeats):
            band, end = walk(codes, starts, profile, r)
            inside = end <= (begin + sizes)[own]
            valid = np.maximum(valid, np.bincount(own[inside], minlength=len(texts)))
            order = np.flatnonzero(inside)[np.argsort(band[inside], kind="stable")]
            band = band[order]
            bits = np.zeros(1 << max(16, int(32 * len(band)).bit_length()), dtype=bool)
            bits[band & np.uint32(len(bits) - 1)] = True
            self.tables.append((band, items[own[order]], (starts - begin[own])[order], bits))
        #: bands of different starts that an item must share; few where it has few.
        self.need = dict(zip(items.tolist(), np.where(valid < 6, 1, profile.need).tolist(), strict=True))

    def hits(self, codes: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(item, offset in the item, place) of all shared bands."""
        found = []
        for r, (bands, item, offset, bits) in enumerate(self.tables):
            got, _ = walk(codes, starts, self.profile, r)
            maybe = np.flatnonzero(bits.take(got & np.uint32(len(bits) - 1)))
            lo, hi = np.searchsorted(bands, got[maybe], side="left"), np.searchsorted(bands, got[maybe], side="right")
            n = hi - lo
            flat = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(lo, n)
            found.append((item[flat], offset[flat], np.repeat(starts[maybe], n)))
        return tuple(np.concatenate([f[k] for f in found]) for k in range(3))


class Items:
    """A block of the benchmark: texts, bands and bit masks of its items."""

    def __init__(self, rows: list[tuple[int, str]]):
        kept = [(i, x) for i, t in rows if (x := normal(t))]
        self.ids, self.texts = [i for i, _ in kept], [x for _, x in kept]
        self.sizes = np.array([len(x) for x in self.texts], dtype=np.int64)
        self.most = (DISTANCE * self.sizes + 1e-9).astype(np.int64)
        self.words = [x.count(b" ") + 1 for x in self.texts]
        kinds = (np.flatnonzero(self.sizes >= LONG), np.flatnonzero((self.sizes >= TINY) & (self.sizes < LONG)))
        self.bands = [Bands([self.texts[k] for k in of], of, p) for of, p in zip(kinds, PROFILES, strict=True) if len(of)]
        self.tiny = np.flatnonzero(self.sizes < TINY).tolist()
        self._masks: dict[int, tuple[np.ndarray, dict[int, int]]] = {}

    def masks(self, words: int, wanted: np.ndarray) -> tuple[np.ndarray, dict[int, int]]:
        """Bit masks of the wanted items of so many 64-bit words, and the row of each."""
        out, place = np.zeros((len(wanted), 256, words), dtype=np.uint64), {int(k): r for r, k in enumerate(wanted)}
        for k, r in place.items():
            for at, c in enumerate(self.texts[k]):
                out[r, c, at >> 6] |= np.uint64(1 << (at & 63))
        return out, place

    def windows(self, bands: Bands, data: bytes, begin: np.ndarray) -> np.ndarray:
        """Rows (document, item, step of place): item-sized windows with enough shared bands, each once."""
        t, codes = coded(data)
        starts = np.flatnonzero(t > 0) if bands.profile.every_byte else word_starts(t)
        out = []
        for lo in range(0, len(starts), 1 << 18):  # a window over a cut is found by what lies on either side
            part = starts[max(0, lo - (1 << 10)) : lo + (1 << 18)]
            item, offset, place = bands.hits(codes, part)
            if not len(item):
                continue
            doc = np.searchsorted(begin, place, side="right") - 1
            diagonal = place - offset
            order = np.lexsort((offset, diagonal, item, doc))
            doc, item, offset, diagonal = doc[order], item[order], offset[order], diagonal[order]
            need = np.array([bands.need[k] for k in item.tolist()])
            near = (doc[1:] == doc[:-1]) & (item[1:] == item[:-1]) & (offset[1:] != offset[:-1]) & (diagonal[1:] - diagonal[:-1] <= self.most[item[1:]] + 1)
            keep = need < 2
            keep[:-1] |= near
            step = np.maximum(16, self.sizes[item[keep]] // 4)
            out.append(np.unique(np.stack([doc[keep], item[keep], (diagonal[keep] - begin[doc[keep]]) // step], axis=1), axis=0))
        return np.unique(np.concatenate(out), axis=0) if out else np.zeros((0, 3), np.int64)

    def verified(self, texts: list[bytes], rows: np.ndarray):
        """(document, item, distance, end in text) of the windows that hold a match."""
        doc, item = rows[:, 0], rows[:, 1]
        step = np.maximum(16, self.sizes[item] // 4)
        lo = np.maximum(0, rows[:, 2] * step - self.most[item])
        hi = (rows[:, 2] + 1) * step + self.sizes[item] + 2 * self.most[item]
        words = -(-self.sizes[item] // 64)
        for w in np.unique(words).tolist():
            mine = np.flatnonzero(words == w)
            for at in range(0, len(mine), 4096):
                part = mine[at : at + 4096]
                if w > 32 or len(part) < 8:
                    for k in part.tolist():
                        got = within(self.texts[item[k]], texts[doc[k]][lo[k] : hi[k]], int(self.most[item[k]]))
                        if got:
                            yield int(doc[k]), int(item[k]), got[0], int(lo[k]) + got[1]
                    continue
                masks, place = self.masks(w, np.unique(item[part]))
                shown = [texts[doc[k]][lo[k] : hi[k]] for k in part.tolist()]
                width = max(map(len, shown))
                grid = np.frombuffer(b"".join(s.ljust(width, b"\0") for s in shown), dtype=np.uint8).reshape(-1, width)
                which = np.array([place[k] for k in item[part].tolist()])
                wanted = np.zeros(len(masks), dtype=np.int64)
                wanted[list(place.values())] = self.sizes[list(place)]
                best, end = distances(masks, wanted, which, grid)
                for k in np.flatnonzero(best <= self.most[item[part]]).tolist():
                    yield int(doc[part[k]]), int(item[part[k]]), int(best[k]), int(lo[part[k]]) + int(end[k])

    def matches(self, texts: list[str | None]):
        """(document, item id, distance, item bytes, first word, words) of every item found in a text; the best place of each."""
        docs = [normal(t) for t in texts]
        best: dict[tuple[int, int], tuple[int, int]] = {}

        def offer(d, k, distance, end):
            best[d, k] = min((distance, end), best.get((d, k), (1 << 60, 0)))

        for group in grouped(docs):
            mine = [docs[d] for d in group]
            begin = np.cumsum([0, *(len(x) + 1 for x in mine)])[:-1]
            for bands in self.bands:
                for d, *rest in self.verified(mine, self.windows(bands, b"\0".join(mine) + b"\0", begin)):
                    offer(group[d], *rest)
        for k in self.tiny:
            for d, text in enumerate(docs):
                if text and (got := within(self.texts[k], text, int(self.most[k]))):
                    offer(d, k, *got)
        return [(d, self.ids[k], dist, len(self.texts[k]), docs[d].count(b" ", 0, max(0, end - len(self.texts[k]))), self.words[k]) for (d, k), (dist, end) in sorted(best.items())]


def grouped(docs: list[bytes]) -> Iterator[list[int]]:
    """Places of texts that hold about GROUP_BYTES together; a longer text is a group of its own."""
    group, size = [], 0
    for d, text in enumerate(docs):
        if text:
            if size and size + len(text) > GROUP_BYTES:
                yield group
                group, size = [], 0
            group.append(d)
            size += len(text)
    if group:
        yield group


def blocks(benchmark: DataFrame) -> Iterator[list[tuple[int, str]]]:
    """The benchmark's items in blocks of about BLOCK_CHARS; the driver reads one at a time."""
    items = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("bigint").alias("item_id"), "text")
    chars = items.agg(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0]
    n = 1 + int(chars) // BLOCK_CHARS
    for b in range(n):
        yield [tuple(r) for r in items.where(F.pmod(F.xxhash64("item_id"), F.lit(n)) == b).distinct().orderBy("item_id", "text").collect()]


def contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, item_id, distance, similarity, first_word, n_words): items found in documents."""
    spark, out = docs.sparkSession, None
    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, item_id bigint, distance bigint, similarity double, first_word bigint, n_words bigint"
    for rows in blocks(benchmark):
        shared = spark.sparkContext.broadcast(rows)

        def find(batches, shared=shared):
            items = Items(shared.value)
            for b in batches:
                got = items.matches(b.column(1).to_pylist())
                cols = list(zip(*got, strict=True)) if got else [[]] * 6
                ids = b.column(0).take(pa.array(cols[0], pa.int64()))
                like = [1 - d / n for d, n in zip(cols[2], cols[3], strict=True)]
                yield pa.RecordBatch.from_arrays([ids, pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int64()), pa.array(like, pa.float64()), pa.array(cols[4], pa.int64()), pa.array(cols[5], pa.int64())], names=["doc_id", "item_id", "distance", "similarity", "first_word", "n_words"])

        part = docs.select("doc_id", "text").mapInArrow(find, schema)
        out = part if out is None else out.unionByName(part)
    return out


def clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """``docs`` without the documents in which an item is found; all columns stay. Judged row by row, without a join."""
    spark, names = docs.sparkSession, docs.columns
    for rows in blocks(benchmark):
        shared = spark.sparkContext.broadcast(rows)

        def keep(batches, shared=shared):
            items = Items(shared.value)
            for b in batches:
                bad = {m[0] for m in items.matches(b.column(names.index("text")).to_pylist())}
                yield b.filter(pa.array([i not in bad for i in range(b.num_rows)], pa.bool_()))

        docs = docs.mapInArrow(keep, docs.schema)
    return docs
