"""Byte-level BPE by a distinct-word table.

1. Spark splits every text into words by the vocabulary's pattern. Runs of documents form units of
   about ``UNIT_WORDS`` words; a unit keeps its distinct words once and each document the places of
   its words among them, so a word that fills a corpus is one entry a unit.
2. Units deal their distinct words out by hash. The buckets are the table of the distinct words of
   all documents: each word, rare or frequent, stands in one bucket and is encoded there exactly once.
3. A bucket answers a unit in the order in which it was asked, so ids join back to words by position
   alone, and words to documents by their places.
4. Ids are decoded by a join with the vocabulary's pieces, which are keyed by id.

Null text is an empty text: no ids, empty digests. Repeated rows give repeated results, an empty
table gives no rows, other columns are ignored. Special tokens in a text are one id each, as in the
library; a vocabulary whose special tokens can overlap one another is refused.
"""

from __future__ import annotations

import hashlib
import json
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, gathered, squeeze, unsqueeze

#: Fixed value: the word pattern of the byte-level vocabulary; S stands for white space.
WORDS = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^S\p{L}\p{N}]+|[S]+(?![^S])|[S]+".replace("S", r"\p{IsWhite_Space}")
#: Words of a unit, about: what one task holds of places (4 bytes each) and of distinct words; bytes of texts for each bucket of the table.
UNIT_WORDS, BUCKET_BYTES = 1 << 22, 64 << 20
#: Effort of compression: payloads are written twice and take little time to pack.
LEVEL = 9


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


class Vocabulary:
    """Pieces, ranks and special tokens read from a tokenizer file; built on driver and workers alike."""

    def __init__(self, path: str):
        spec = json.load(open(path, encoding="utf-8"))
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        hidden = [b for b in range(256) if b not in set(shown)]
        byte_of = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"] if t["special"]}
        self.ids = {bytes(byte_of[c] for c in piece): i for piece, i in spec["model"]["vocab"].items()}
        self.pieces = {i: p for p, i in self.ids.items()} | {i: s.encode() for s, i in self.special.items()}
        for a in self.special:
            if any(a != b and a in b or any(a.endswith(b[:k]) for k in range(1, len(b))) for b in self.special):
                raise ValueError("special tokens that overlap can't be split at")
        import tiktoken

        # words come split, so the pattern here only has to take each as a whole
        own = tiktoken.Encoding("own", pat_str=r"[\s\S]+", mergeable_ranks=self.ids, special_tokens={})
        self.merge = own._core_bpe.encode_single_piece

    def encode_word(self, word: str) -> list[int]:
        return [self.special[word]] if word in self.special else self.merge(word.encode())


@lru_cache(maxsize=2)
def vocabulary(path: str) -> Vocabulary:
    return Vocabulary(path)


def words(text: Column, special: list[str]) -> Column:
    """The words of a text in order, split by Spark; a special token is a word of its own."""
    plain = F.regexp_extract_all(text, F.lit(WORDS), F.lit(0))
    if special:
        any_of = "|".join(rf"\Q{s}\E" for s in special)
        parts = F.split(text, f"(?={any_of})|(?<={any_of})", -1)
        apart = F.flatten(F.transform(parts, lambda p: F.when(p.isin(special), F.array(p)).otherwise(F.regexp_extract_all(p, F.lit(WORDS), F.lit(0)))))
        plain = F.when(text.rlike(any_of), apart).otherwise(plain)
    return F.coalesce(plain, F.array().cast("array<string>"))


def strings(lengths: np.ndarray, data: np.ndarray) -> pa.LargeStringArray:
    ends = np.concatenate([[0], np.cumsum(lengths, dtype=np.int64)])
    return pa.LargeStringArray.from_buffers(len(lengths), pa.py_buffer(ends.tobytes()), pa.py_buffer(data.tobytes()))


def parts_of(words: pa.LargeStringArray) -> tuple[np.ndarray, np.ndarray]:
    """(lengths, bytes) of an array without nulls."""
    if not len(words):
        return np.zeros(0, np.int64), np.zeros(0, np.uint8)
    ends = np.frombuffer(words.buffers()[1], np.int64)[words.offset : words.offset + len(words) + 1]
    data = words.buffers()[2]
    return np.diff(ends), np.frombuffer(data, np.uint8)[ends[0] : ends[-1]] if data is not None else np.zeros(0, np.uint8)


def by_count(often: np.ndarray) -> np.ndarray:
    """Order from the most frequent on, so that places of words are small numbers."""
    return np.argsort(-often.astype(np.int64), kind="stable")


def units(docs: DataFrame, keep: list[str], path: str, buckets: int) -> DataFrame:
    """(unit, bucket, payload). Of each unit one row of bucket -1 for its documents: their kept columns, how many words
    each has, the places of these among the unit's distinct words from the most frequent on, and how often each of these occurs,
    in the order of buckets; and one row a bucket with the distinct words that it is asked for."""

    def index(batches):
        part, n, held, size = TaskContext.get().partitionId() << 32, 0, [], 0

        def settle():
            rows = pa.Table.from_batches([b.select(list(range(len(keep)))) for b in held]).combine_chunks()
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, rows.schema) as out:
                out.write_table(rows)
            counts = np.concatenate([np.diff(b.column(len(keep)).offsets.to_numpy()) for b in held])
            coded = pa.concat_arrays([b.column(len(keep)).flatten().cast(pa.large_string()) for b in held]).dictionary_encode()
            places, distinct = coded.indices.to_numpy(), coded.dictionary
            bucket = (pd.util.hash_array(distinct.to_numpy(zero_copy_only=False), categorize=False) % np.uint64(buckets)).astype(np.int64) if len(distinct) else places
            order = np.argsort(bucket, kind="stable")
            distinct, bucket = distinct.take(pa.array(order)), bucket[order]
            often = np.bincount(places, minlength=len(order))[order]
            rank = np.empty(len(order), dtype=np.int64)
            rank[order[by_count(often)]] = np.arange(len(order))
            cuts = np.concatenate([[0], np.flatnonzero(np.diff(bucket)) + 1, [len(bucket)]]) if len(bucket) else np.zeros(1, np.int64)
            names, payloads = [-1], [squeeze(np.frombuffer(sink.getvalue(), np.uint8), counts, rank[places], often, level=LEVEL)]
            for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                names.append(int(bucket[lo]))
                payloads.append(squeeze(*parts_of(distinct.slice(lo, hi - lo)), level=LEVEL))
            return pa.RecordBatch.from_arrays([pa.array([part + n] * len(names), pa.int64()), pa.array(names, pa.int32()), pa.array(payloads, pa.binary())], names=["unit", "bucket", "payload"])

        for b in batches:
            if b.num_rows:
                held.append(b)
                size += len(b.column(len(keep)).flatten())
                if size >= UNIT_WORDS:
                    yield settle()
                    n, held, size = n + 1, [], 0
        if held:
            yield settle()

    split = docs.select(*keep, words(F.col("text"), sorted(vocabulary(path).special)).alias("_words"))
    return split.mapInArrow(index, "unit bigint, bucket int, payload binary")


def word_table(asked: DataFrame, path: str) -> DataFrame:
    """(unit, bucket, payload, n_words): for each unit that asked a bucket the ids of its words, in its order. Every distinct
    word of a bucket is encoded once; n_words says how many there are, on the first row of a bucket."""

    def encode(batches):
        v = vocabulary(path)

        def settle(bucket, rows):
            lists = [strings(*unsqueeze(payload)) for _, payload in rows]
            coded = pa.concat_arrays(lists).dictionary_encode()
            ids = pa.array(list(map(v.encode_word, coded.dictionary.to_pylist())), pa.list_(pa.int32()))
            at = 0
            for (unit, _), mine in zip(rows, lists, strict=True):
                got = ids.take(coded.indices.slice(at, len(mine)))
                n = len(ids) if not at else 0
                at += len(mine)
                payload = squeeze(got.value_lengths().to_numpy(), got.flatten().to_numpy(), level=LEVEL)
                yield pa.RecordBatch.from_arrays([pa.array([unit], pa.int64()), pa.array([bucket], pa.int32()), pa.array([payload], pa.binary()), pa.array([n], pa.int64())], names=["unit", "bucket", "payload", "n_words"])

        yield from gathered(batches, settle)

    dealt = asked.select("bucket", "unit", "payload").repartition("bucket").sortWithinPartitions("bucket", "unit")
    return dealt.mapInArrow(encode, "unit bigint, bucket int, payload binary, n_words bigint")


FIELDS = (("n_tokens", "bigint"), ("ids_sha256", "string"), ("decoded_sha256", "string"))


def encode_decode(docs: DataFrame, path: str | None = None, keep=("doc_id",), with_ids: bool = True, with_text: bool = True) -> DataFrame:
    """``keep`` columns, n_tokens and the digests of ids and decoded text, with ids array<int> and
    decoded string if they are wanted."""
    path, keep = path or default_vocabulary(), list(keep)
    size = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    indexed = cut(units(docs, keep, path, 1 + size // BUCKET_BYTES))
    answers = word_table(indexed.where("bucket >= 0"), path)
    fields = [*FIELDS, *[("ids", "array<int>")] * with_ids, *[("decoded", "string")] * with_text]
    kept = T.StructType([docs.schema[k] for k in keep])

    def join(left: pa.Table, right: pa.Table) -> pa.Table:
        kept_rows, counts, places, often = unsqueeze(left.column("payload")[0].as_py())
        rows = pa.ipc.open_stream(kept_rows.tobytes()).read_all()
        got = [unsqueeze(p) for _, p in sorted(zip(right.column("bucket").to_pylist(), right.column("payload").to_pylist(), strict=True))]
        length, flat = (np.concatenate([g[i] for g in got]) if got else np.zeros(0, np.int64) for i in (0, 1))
        ids = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(length)]), pa.int32()), pa.array(flat, pa.int32()))
        ids = ids.take(pa.array(by_count(often)))
        pieces, numbers = spelling(path)
        size = ids.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
        ends = np.concatenate([[0], np.cumsum(counts)])
        upto = np.concatenate([[0], np.cumsum(size[places])])[ends]
        tokens = ids.take(pa.array(places)).flatten()
        digests = [hashlib.sha256(a[:-1]).hexdigest() for a in slices(numbers, tokens, upto)]
        texts, decoded = [], []
        for a in slices(pieces, tokens, upto):
            try:
                said = str(a, "utf-8")
            except UnicodeDecodeError:
                said = bytes(a).decode("utf-8", "replace")
                a = said.encode()
            decoded.append(hashlib.sha256(a).hexdigest())
            if with_text:
                texts.append(said)
        cols = [*(c.combine_chunks() for c in rows.columns), pa.array(np.diff(upto)), pa.array(digests, pa.string()), pa.array(decoded, pa.string())]
        cols += [pa.ListArray.from_arrays(pa.array(upto, pa.int32()), tokens)] * with_ids + [pa.array(texts, pa.string())] * with_text
        return pa.table(cols, names=[*keep, *(n for n, _ in fields)])

    schema = T.StructType([*kept, *T.StructType.fromDDL(", ".join(f"{n} {t}" for n, t in fields))])
    documents = indexed.where("bucket < 0").select(F.col("unit").alias("of"), "payload")
    return documents.groupBy("of").cogroup(answers.groupBy("unit")).applyInArrow(join, schema)


@lru_cache(maxsize=2)
def spelling(path: str) -> tuple[pa.LargeBinaryArray, pa.LargeBinaryArray]:
    """(bytes, number and comma) of every id; an id is its row."""
    pieces = vocabulary(path).pieces
    top = max(pieces) + 1
    return pa.array([pieces.get(i, b"") for i in range(top)], pa.large_binary()), pa.array([f"{i},".encode() for i in range(top)], pa.large_binary())


def slices(parts: pa.LargeBinaryArray, tokens: pa.Array, ends: np.ndarray):
    """The bytes of each document: its tokens' parts, one after the other."""
    taken = parts.take(tokens)
    if not len(taken):
        yield from (b"" for _ in ends[1:])
        return
    at = np.frombuffer(taken.buffers()[1], np.int64)[taken.offset :][ends]
    data = memoryview(taken.buffers()[2])
    for lo, hi in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        yield data[lo:hi]
