"""Language ID by segmentation-marginalised unigrams.

The pieces of a fixed public vocabulary get a probability in each language. A word's probability
is the sum over all its segmentations into pieces, by the forward algorithm; a text's is the
product over its words (runs of letters, lower case). Piece probabilities are fitted by
expectation-maximisation over the same sums.

The fit uses a bounded sample: of each language the labelled documents whose hash of the id falls into the
share that makes about ``SAMPLE`` of them. Prediction reads whole texts of all documents and nothing but text.

Null text or text without a letter is ``und`` with score 0. With no labelled rows all is ``und``.
Rows with null lang don't train; ties between languages go to the first in order of names;
repeated rows give repeated results; an empty table gives no rows; other columns are ignored.
Letters are what Unicode calls so (categories L*). Words of any length are summed whole, very long ones in logarithms.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import apart, map_batches

SAMPLE, EM_ROUNDS = 400, 3
FLOOR = 1e-7
#: Words of this many letters or more are summed one by one, in logarithms; words scored at once; words a task remembers.
LONG, CHUNK, OWN = 64, 4096, 1 << 18
#: What \w takes for a word's sign though it is no letter: numbers that are no decimal digits.
NUMBERS = "".join(c for c in map(chr, range(0x110000)) if c.isalnum() and not c.isalpha() and not c.isdecimal())
LETTERS = re.compile(rf"[^\W\d_{NUMBERS}]+")
SIGNS = re.compile(r"[^\W\d_]+")
START = "▁"


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def words_of(text: str) -> list[str]:
    text = text.lower()
    found = SIGNS.findall(text)
    return found if "".join(found).isalpha() else LETTERS.findall(text)


class Pieces:
    """The vocabulary's pieces that can stand in a word of lower-case letters, found by rolling hashes."""

    def __init__(self, path: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces = {sp.id_to_piece(i) for i in range(sp.get_piece_size()) if sp.is_byte(i) == sp.is_control(i) == sp.is_unknown(i)}
        kept = {p for p in pieces if p == p.lower() and (p.removeprefix(START) == "" or LETTERS.fullmatch(p.removeprefix(START)))} | {START}
        self.names = sorted(kept)
        self.longest = max(map(len, self.names))
        self.place = {p: i for i, p in enumerate(self.names)}
        self.power = np.array([pow(0x9E3779B97F4A7C15, k + 1, 1 << 64) for k in range(self.longest)], dtype=np.uint64)
        keys = np.array([self._key(p) for p in self.names], dtype=np.uint64)
        self.order = np.argsort(keys)
        self.keys = keys[self.order]
        # beginnings of pieces by 20 bits of their hash: what isn't among them isn't looked up or read on
        begun = np.array([self._key(p[:k]) for p in self.names for k in range(1, len(p) + 1)], dtype=np.uint64)
        self.begins = np.zeros(1 << 20, dtype=bool)
        self.begins[self._short(begun)] = True

    @staticmethod
    def _short(h: np.ndarray) -> np.ndarray:
        return ((h ^ h >> np.uint64(32)) * np.uint64(0xD6E8FEB86659FD93) >> np.uint64(44)).astype(np.int64)

    def _key(self, piece: str) -> int:
        return sum(ord(c) * int(self.power[k]) for k, c in enumerate(piece)) % (1 << 64)

    def chunks(self, words: list[str]):
        """(rows, sizes, found) for words under LONG letters, of like length together."""
        lengths = np.array([len(w) for w in words])
        order = np.argsort(lengths, kind="stable")
        order = order[lengths[order] < LONG]
        for at in range(0, len(order), CHUNK):
            rows = order[at : at + CHUNK]
            yield rows, *self.spans([words[k] for k in rows])

    def spans(self, words: list[str]):
        """(lengths, [(start, length, rows, piece ids)]): every place where a piece stands in a word."""
        sizes = np.array([len(w) + 1 for w in words])
        width = int(sizes.max())
        flat = np.frombuffer("".join((START + w).ljust(width, "\0") for w in words).encode("utf-32-le"), dtype=np.uint32).reshape(-1, width)
        cols = [np.ascontiguousarray(flat[:, k]).astype(np.uint64) for k in range(width)]
        found = []
        for i in range(width):
            live = np.flatnonzero(sizes > i)
            h = np.zeros(len(live), dtype=np.uint64)
            for n in range(1, min(self.longest, width - i) + 1):
                fits = sizes[live] >= i + n
                if not fits.all():
                    live, h = live[fits], h[fits]
                if not len(live):
                    break
                h = h + cols[i + n - 1][live] * self.power[n - 1]
                goes_on = self.begins.take(self._short(h))
                if n == 1 and not goes_on.all():
                    found.append((i, 1, live[~goes_on], np.full((~goes_on).sum(), len(self.names))))
                live, h = live[goes_on], h[goes_on]
                at = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
                hit = self.keys[at] == h
                if hit.any():
                    found.append((i, n, live[hit], self.order[at[hit]]))
                if n == 1 and not hit.all():
                    found.append((i, 1, live[~hit], np.full((~hit).sum(), len(self.names))))
        return sizes, found

    def forward(self, sizes, found, probs: np.ndarray) -> np.ndarray:
        """alpha[row, position, language]; ``probs`` has a last row for signs without a piece."""
        alpha = np.zeros((len(sizes), int(sizes.max()) + 1, probs.shape[1]))
        alpha[:, 0] = 1
        for i, n, rows, ids in found:  # found is in order of starts, so alpha[i] is complete
            alpha[rows, i + n] += alpha[rows, i] * probs[ids]
        return alpha

    def long_spans(self, word: str) -> list[tuple[int, int, int]]:
        """(start, end, piece id) of one word."""
        signs, out = START + word, []
        for i in range(len(signs)):
            got = [(i, i + n, self.place[p]) for n in range(1, min(self.longest, len(signs) - i) + 1) if (p := signs[i : i + n]) in self.place]
            if not got or got[0][1] > i + 1:
                got.insert(0, (i, i + 1, len(self.names)))
            out += got
        return out

    @staticmethod
    def log_sums(spans, size: int, logs: np.ndarray, backward: bool = False) -> np.ndarray:
        """Logarithms of the sums over all segmentations up to each position, or from it on."""
        out = np.full((size + 1, logs.shape[1]), -np.inf)
        out[size if backward else 0] = 0
        for i, j, piece in reversed(spans) if backward else spans:
            a, b = (i, j) if backward else (j, i)
            out[a] = np.logaddexp(out[a], out[b] + logs[piece])
        return out

    def word_scores(self, words: list[str], probs: np.ndarray) -> np.ndarray:
        out = np.empty((len(words), probs.shape[1]))
        for rows, sizes, found in self.chunks(words):
            alpha = self.forward(sizes, found, probs)
            out[rows] = np.log(np.maximum(alpha[np.arange(len(rows)), sizes], 1e-300))
        for k, w in enumerate(words):
            if len(w) >= LONG:
                out[k] = self.log_sums(self.long_spans(w), len(w) + 1, np.log(probs))[-1]
        return out

    def fit(self, counts: list[dict[str, int]]) -> np.ndarray:
        """Piece probabilities (pieces + 1, languages) from word counts by language."""
        n = len(self.names)
        columns = []
        for words in counts:
            names, weights = list(words), np.array(list(words.values()), dtype=float)
            parts = list(self.chunks(names))
            longs = [(k, len(w) + 1, self.long_spans(w)) for k, w in enumerate(names) if len(w) >= LONG]
            probs = np.full((n + 1, 1), 1.0 / n)
            for _ in range(EM_ROUNDS):
                expected = np.full(n + 1, 0.5)
                for where, sizes, found in parts:
                    alpha = self.forward(sizes, found, probs)[:, :, 0]
                    beta = np.zeros_like(alpha)
                    rows = np.arange(len(sizes))
                    beta[rows, sizes] = 1
                    for i, k, r, ids in reversed(found):
                        beta[r, i] += probs[ids, 0] * beta[r, i + k]
                    scale = weights[where] / np.maximum(alpha[rows, sizes], 1e-300)
                    for i, k, r, ids in found:
                        expected += np.bincount(ids, alpha[r, i] * probs[ids, 0] * beta[r, i + k] * scale[r], minlength=n + 1)
                for k, size, spans in longs:
                    logs = np.log(probs)
                    a, b = (self.log_sums(spans, size, logs, back)[:, 0] for back in (False, True))
                    for i, j, piece in spans:
                        expected[piece] += weights[k] * np.exp(a[i] + logs[piece, 0] + b[j] - a[size])
                probs = (expected / expected[:n].sum())[:, None]
                probs[n] = FLOOR
            columns.append(probs)
        return np.hstack(columns) if columns else np.zeros((n + 1, 0))


def held_out(doc_id: str = "doc_id"):
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, path: str, sample: int = SAMPLE) -> tuple[list[str], np.ndarray]:
    """(languages, piece probabilities) from the bounded sample of labelled rows that are not held out."""
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull() & ~held_out())
    sizes = labelled.groupBy("lang").agg(F.count(F.lit(1)).alias("n"))  # one row a language
    share = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 31)) * F.col("n").cast("double") < F.lit(float(sample << 31))
    chosen = labelled.select("doc_id", "lang", "text").join(F.broadcast(sizes), "lang").where(share)

    def count(batches):
        for b in batches:
            c = Counter((lang, w) for lang, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True) for w in words_of(t))
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in c], pa.string()), pa.array([k[1] for k in c], pa.string()), pa.array(list(c.values()), pa.int64())], names=["lang", "word", "n"])

    rows = chosen.select("lang", "text").mapInArrow(count, "lang string, word string, n bigint").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    by: dict[str, dict[str, int]] = {}
    for r in rows.toLocalIterator():
        by.setdefault(r.lang, {})[r.word] = r.n
    langs = sorted(by)
    return langs, Pieces(path).fit([dict(sorted(by[k].items())) for k in langs])


def predict(docs: DataFrame, model: tuple[list[str], np.ndarray], path: str, keep=("doc_id",)) -> DataFrame:
    """``keep`` columns, lang_pred, score: the share of the best language in the sum over all."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run():
        pieces = Pieces(path)
        langs, probs = shared.value
        place: dict[str, int] = {}
        table = np.zeros((0, len(langs)))

        def work(texts):
            nonlocal table
            if len(place) > OWN:
                place.clear()
                table = table[:0]
            texts = [words_of(t) if t else [] for t in texts]
            new = list({w for ws in texts for w in ws if w not in place})
            if new and langs:
                place.update(zip(new, range(len(place), len(place) + len(new)), strict=True))
                table = np.vstack([table, pieces.word_scores(new, probs)])
            names, scores = [], []
            for ws in texts:
                if not ws or not langs:
                    names.append("und")
                    scores.append(0.0)
                    continue
                total = table[np.fromiter(map(place.__getitem__, ws), dtype=np.int64, count=len(ws))].sum(axis=0)
                best = int(total.argmax())
                names.append(langs[best])
                scores.append(float(1 / np.exp(total - total[best]).sum()))
            return [names, scores]

        return work

    return map_batches(docs, list(keep), ["text"], [T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())], run)


def identify(docs: DataFrame, path: str | None = None, keep=("doc_id",), sample: int = SAMPLE) -> DataFrame:
    path = path or default_vocabulary()
    return predict(docs, fit(docs, path, sample), path, keep)


def keep_identified(docs: DataFrame, path: str | None = None) -> DataFrame:
    """``docs`` without the documents that have no language; all columns stay, whatever their names."""
    path = path or default_vocabulary()
    inner, back = apart(docs, ("doc_id", "text", "lang"))
    judged = predict(inner, fit(docs, path), path, keep=inner.columns)
    return back(judged.where("lang_pred <> 'und'"))
