"""Language-model scoring by cross-entropy difference.

Two bigram models share order, smoothing and one vocabulary, the words of the whole corpus. The target
model counts the documents that the labels call good, the background model all documents; its counts
are scaled to the target's number of tokens, so that smoothing weighs alike in both. A document's score is
the mean over its tokens of the loss under the target model less the loss under the background model;
low scores look like the target.

Every word and every pair of words is counted; tables of counts grow with the corpus and are never on the
driver nor broadcast. Runs of documents form units of about ``UNIT_TOKENS`` tokens. A unit deals the keys
of its distinct words and pairs, with their counts, out by ranges of keys; a bucket sums the counts of a
key over all units and answers each unit in the order in which it was asked; the unit then scores its
documents. A frequent pair is one entry a unit. Keys are 55 bits of a hash.

P(w | v) = (n(v w) + PRIOR P(w)) / (n(v) + PRIOR) and P(w) = (n(w) + 1) / (tokens + words). A document
starts after a mark of its own; what n(v) counts at ends of documents is left to the end.

Null or blank text has no tokens and null losses. Documents without a label or of a null id count in the
background only; several labels count as good if one is. Repeated rows count repeatedly. Without good
documents both models are uniform. An empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, gathered, squeeze, unsqueeze

PRIOR = 50.0
#: Tokens of a unit, about; bytes of text for each bucket of keys.
UNIT_TOKENS, BUCKET_BYTES = 1 << 21, 16 << 20
#: Good ids that may be broadcast, 8 bytes each; more are joined by a shuffle.
BROADCAST_IDS = 1 << 20
KEY_BITS = 56


def tokens(text: str) -> list[str]:
    return text.lower().split()


def deltas(ordered: np.ndarray) -> np.ndarray:
    return np.diff(ordered.astype(np.uint64), prepend=np.uint64(0))


class Unit:
    """Documents by their pairs: for each document the sorted places of its pairs among the unit's sorted distinct pairs
    (v * (words + 1) + w, v = 0 at the start), the hashes of its sorted distinct words, and which documents are good."""

    def __init__(self, sizes, words, pairs, places, good):
        self.sizes, self.words, self.pairs, self.places, self.good = sizes, words, pairs, places, good

    @classmethod
    def of(cls, lists: list[pa.LargeStringArray], sizes: np.ndarray, good: np.ndarray) -> Unit:
        coded = pa.concat_arrays(lists).dictionary_encode()
        hashes = pd.util.hash_array(coded.dictionary.to_numpy(zero_copy_only=False), categorize=False) if len(coded.dictionary) else np.zeros(0, np.uint64)
        words, rank = np.unique(hashes, return_inverse=True)
        word = rank[coded.indices.to_numpy()].astype(np.int64) + 1
        before = np.concatenate([[0], word[:-1]]) if len(word) else word
        ends = np.cumsum(sizes)
        before[(ends - sizes)[sizes > 0]] = 0
        pairs, places = np.unique(before * (len(words) + 1) + word, return_inverse=True)
        doc = np.repeat(np.arange(len(sizes)), sizes)
        ordered = np.sort(doc * len(pairs) + places)
        return cls(sizes, words, pairs, ordered - doc * len(pairs), good)

    def pack(self) -> bytes:
        step = np.diff(self.places, prepend=0)
        first = (np.cumsum(self.sizes) - self.sizes)[self.sizes > 0]
        step[first] = self.places[first]
        return squeeze(self.sizes, deltas(self.words), deltas(self.pairs), step.astype(np.uint32), self.good.astype(np.uint8))

    @classmethod
    def unpack(cls, data: bytes) -> Unit:
        sizes, words, pairs, step, good = unsqueeze(data)
        total = np.cumsum(step.astype(np.int64))
        first = np.cumsum(sizes) - sizes
        base = np.where(sizes > 0, (total - step)[np.minimum(first, max(len(step) - 1, 0))] if len(step) else 0, 0)
        return cls(sizes, np.cumsum(words, dtype=np.uint64), np.cumsum(pairs, dtype=np.uint64).astype(np.int64), total - np.repeat(base, sizes), good.astype(bool))

    def split(self) -> tuple[np.ndarray, np.ndarray]:
        """The two words of each pair as places, 0 for the start."""
        return np.divmod(self.pairs, len(self.words) + 1)

    def keys(self) -> np.ndarray:
        """Keys of the words, then of the pairs; the last bit tells which."""
        hashes = np.concatenate([np.array([0x243F6A8885A308D3], dtype=np.uint64), self.words])
        v, w = self.split()
        pair = hashes[v] * np.uint64(0x9E3779B97F4A7C15) ^ hashes[w]
        both = np.concatenate([self.words, (pair ^ pair >> np.uint64(32)) * np.uint64(0xD6E8FEB86659FD93)])
        both ^= both >> np.uint64(29)
        kind = np.repeat(np.array([1, 0], dtype=np.uint64), [len(self.words), len(self.pairs)])
        return both >> np.uint64(64 - KEY_BITS) & ~np.uint64(1) | kind

    def counts(self, weight: np.ndarray) -> np.ndarray:
        """How often each key occurs in documents of a weight of one."""
        pair = np.bincount(self.places, weights=np.repeat(weight, self.sizes).astype(float), minlength=len(self.pairs))
        word = np.bincount(self.split()[1] - 1, weights=pair, minlength=len(self.words))
        return np.concatenate([word, pair]).astype(np.int64)

    def losses(self, n: np.ndarray, starts: float, total: float, words: int) -> np.ndarray:
        """Mean loss of each document in bits a token, from counts of its words and pairs; NaN without tokens."""
        v, w = self.split()
        word, pair = n[: len(self.words)], n[len(self.words) :]
        single = (word[w - 1] + 1) / (total + words)
        loss = -np.log2((pair + PRIOR * single) / (np.concatenate([[starts], word])[v] + PRIOR))
        del v, w, single
        some = self.sizes > 0
        summed = np.zeros(len(self.sizes))
        if some.any():
            summed[some] = np.add.reduceat(loss[self.places], (np.cumsum(self.sizes) - self.sizes)[some])
        return np.divide(summed, self.sizes, out=np.full(len(self.sizes), np.nan), where=self.sizes > 0)


def marked(docs: DataFrame, good: DataFrame) -> DataFrame:
    """(doc_id, text, is_good) of every row."""
    ids = good.select(F.col("doc_id").alias("_id")).where("_id is not null").distinct()
    narrow = docs.select("doc_id", "text")
    if ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS:
        ids = F.broadcast(ids)
    else:  # rows of a null id would all meet in one task
        alone = narrow.where("doc_id is null").withColumn("is_good", F.lit(False))
        return narrow.where("doc_id is not null").join(ids, F.col("doc_id") == F.col("_id"), "left").select("doc_id", "text", F.col("_id").isNotNull().alias("is_good")).unionByName(alone)
    return narrow.join(ids, F.col("doc_id") == F.col("_id"), "left").select("doc_id", "text", F.col("_id").isNotNull().alias("is_good"))


def units(rows: DataFrame) -> DataFrame:
    """(unit, ids, payload) and the numbers of tokens and of documents with tokens, of all and of good documents."""

    def index(batches):
        part, n, ids, lists, sizes, good = TaskContext.get().partitionId() << 32, 0, [], [], [], []

        def settle():
            u = Unit.of(lists, np.array(sizes, dtype=np.int64), np.array(good, dtype=bool))
            sink = pa.BufferOutputStream()
            table = pa.Table.from_arrays([pa.chunked_array(ids)], names=["doc_id"])
            with pa.ipc.new_stream(sink, table.schema) as out:
                out.write_table(table)
            facts = [u.sizes.sum(), u.sizes[u.good].sum(), (u.sizes > 0).sum(), (u.sizes[u.good] > 0).sum()]
            return pa.RecordBatch.from_arrays([pa.array([part + n], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary()), pa.array([u.pack()], pa.binary()), *(pa.array([int(x)], pa.int64()) for x in facts)], names=["unit", "ids", "payload", "n", "n_good", "starts", "starts_good"])

        for b in batches:
            said = [tokens(t) if t else [] for t in b.column(1).to_pylist()]
            ids.append(b.column(0))
            lists.append(pa.array([w for ws in said for w in ws], pa.large_string()))
            sizes += map(len, said)
            good += b.column(2).to_pylist()
            del said
            if sum(map(len, lists)) >= UNIT_TOKENS:
                yield settle()
                n, ids, lists, sizes, good = n + 1, [], [], [], []
        if sizes:
            yield settle()

    return rows.mapInArrow(index, "unit bigint, ids binary, payload binary, n bigint, n_good bigint, starts bigint, starts_good bigint")


def ask(indexed: DataFrame, buckets: int) -> DataFrame:
    """(bucket, unit, payload): the sorted keys of a unit with their counts in all and in good documents, by ranges of keys."""

    def send(batches):
        for b in batches:
            for unit, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                u = Unit.unpack(data)
                keys = u.keys()
                order = np.argsort(keys, kind="stable")
                every, good = u.counts(np.ones(len(u.sizes)))[order], u.counts(u.good)[order]
                keys = keys[order]
                bucket = (keys >> np.uint64(KEY_BITS - 32)) * np.uint64(buckets) >> np.uint64(32)
                edges = np.searchsorted(bucket, np.arange(buckets + 1, dtype=np.uint64)) if buckets < len(keys) else np.concatenate([[0], np.flatnonzero(np.diff(bucket)) + 1, [len(keys)]])
                for lo, hi in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
                    if hi > lo:
                        yield pa.RecordBatch.from_arrays([pa.array([int(bucket[lo])], pa.int32()), pa.array([unit], pa.int64()), pa.array([squeeze(deltas(keys[lo:hi]), every[lo:hi], good[lo:hi])], pa.binary())], names=["bucket", "unit", "payload"])

    return indexed.select("unit", "payload").mapInArrow(send, "bucket int, unit bigint, payload binary")


def answer(asked: DataFrame) -> DataFrame:
    """(unit, bucket, payload, words): the counts over all units, in the order of each unit's keys; the first row of a bucket
    says how many distinct words it holds."""

    def add(batches):
        def settle(bucket, rows):
            got = [unsqueeze(payload) for _, payload in rows]
            keys, place = np.unique(np.concatenate([np.cumsum(k, dtype=np.uint64) for k, _, _ in got]), return_inverse=True)
            sums = [np.bincount(place, weights=np.concatenate([g[i] for g in got]), minlength=len(keys)).astype(np.int64) for i in (1, 2)]
            words, at = int((keys & np.uint64(1)).sum()), 0
            for (unit, _), (k, _, _) in zip(rows, got, strict=True):
                mine = place[at : at + len(k)]
                yield pa.RecordBatch.from_arrays([pa.array([unit], pa.int64()), pa.array([bucket], pa.int32()), pa.array([squeeze(*(s[mine] for s in sums))], pa.binary()), pa.array([0 if at else words], pa.int64())], names=["unit", "bucket", "payload", "words"])
                at += len(k)

        yield from gathered(batches, settle)

    return asked.repartition("bucket").sortWithinPartitions("bucket", "unit").mapInArrow(add, "unit bigint, bucket int, payload binary, words bigint")


def score(docs: DataFrame, good: DataFrame) -> DataFrame:
    """doc_id, n_tokens, target_loss, background_loss, score (bits a token) of every row. ``good``: doc_id of the target documents."""
    size = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    indexed = cut(units(marked(docs, good)))
    answers = cut(answer(ask(indexed, 1 + size // BUCKET_BYTES)))
    n, n_good, starts, starts_good = (x or 0 for x in indexed.agg(*(F.sum(c) for c in ("n", "n_good", "starts", "starts_good"))).first())
    words = answers.agg(F.sum("words")).first()[0] or 0
    scale = n_good / n if n else 0.0
    names = ["doc_id", "n_tokens", "target_loss", "background_loss", "score"]

    def join(left: pa.Table, right: pa.Table) -> pa.Table:
        u = Unit.unpack(left.column("payload")[0].as_py())
        got = [unsqueeze(p) for _, p in sorted(zip(right.column("bucket").to_pylist(), right.column("payload").to_pylist(), strict=True))]
        order = np.argsort(u.keys(), kind="stable")

        def counted(i):
            out = np.zeros(len(order))
            if got:
                out[order] = np.concatenate([g[i] for g in got])
            return out

        a = u.losses(counted(1), starts_good, n_good, words)
        b = u.losses(counted(0) * scale, starts * scale, n_good, words)
        ids = pa.ipc.open_stream(left.column("ids")[0].as_py()).read_all().column(0)
        return pa.table([ids.combine_chunks(), pa.array(u.sizes), *(pa.array(x, from_pandas=True) for x in (a, b, a - b))], names=names)

    kind = docs.schema["doc_id"].dataType.simpleString()
    documents = indexed.select(F.col("unit").alias("of"), "ids", "payload")
    return documents.groupBy("of").cogroup(answers.groupBy("unit")).applyInArrow(join, f"doc_id {kind}, n_tokens bigint, target_loss double, background_loss double, score double")
