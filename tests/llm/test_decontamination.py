"""Decontamination: recall of planted edits up to the bound, exact distances, odd items and rows."""

import random
import tracemalloc

import numpy as np
import pytest

from serieslake.llm import decontam
from serieslake.llm.queries import QUERIES


def edited(b: bytes, rate: float, kind: str, rng: random.Random) -> bytes:
    if kind == "every second word":
        words = b.split(b" ")
        for i in range(0, len(words), 2):
            p = rng.randrange(len(words[i]))
            words[i] = words[i][:p] + bytes([97 + (words[i][p] - 96) % 26]) + words[i][p + 1 :]
        return b" ".join(words)
    s = list(b)
    for _ in range(round(rate * len(b))):
        p, k = rng.randrange(len(s)), rng.randrange(3) if kind == "mixed" else 0
        s[p : p + 1] = [[97 + rng.randrange(26)], [s[p], 97 + rng.randrange(26)], []][k]
    return bytes(s)


@pytest.fixture(scope="module")
def items(spark):
    rows = spark.read.parquet("/root/testdata/sf0.1/benchmark.parquet").collect()
    return decontam.Items([(r.item_id, r.text) for r in rows])


@pytest.mark.parametrize(("kind", "rate"), [("every second word", 0), *(("substituted", r) for r in (0.05, 0.1, 0.15, 0.19)), *(("mixed", r) for r in (0.05, 0.1, 0.15, 0.19))])
def test_recall_of_planted_edits(items, kind, rate):
    rng = random.Random(11)
    filler = b"lorem ipsum dolor sit amet consectetur " * 8
    texts = [(filler + edited(x, rate, kind, rng) + b" " + filler).decode("utf-8", "replace") for x in items.texts]
    truth = {k for k, t in enumerate(texts) if decontam.within(items.texts[k], decontam.normal(t), int(items.most[k]))}
    got = {(m[0], m[1]) for m in items.matches(texts)}
    assert len(truth) > 100 and sum((k, items.ids[k]) in got for k in truth) >= 0.97 * len(truth)


def test_matches_equal_all_exact_ones(items):
    """On texts short enough to try every item on each, what is found is what is there, with the least distance."""
    rng = random.Random(3)
    texts = [edited(items.texts[rng.randrange(len(items.texts))], rng.random() * 0.15, "mixed", rng).decode("utf-8", "replace") for _ in range(30)] + ["nothing of that kind here", None, ""]
    want = {(d, items.ids[k]): got[0] for d, t in enumerate(texts) for k, x in enumerate(items.texts) if t and (got := decontam.within(x, decontam.normal(t), int(items.most[k])))}
    assert {(m[0], m[1]): m[2] for m in items.matches(texts)} == want


def test_bit_vectors_give_the_edit_distance():
    rng = random.Random(1)
    texts = [bytes(rng.choice(b"abc ") for _ in range(rng.choice((1, 5, 63, 64, 65, 130)))) for _ in range(40)]
    items = decontam.Items([])
    items.texts, items.sizes = texts, np.array([len(t) for t in texts])
    for words in (1, 2, 3):
        mine = np.flatnonzero(-(-items.sizes // 64) == words)
        masks, place = items.masks(words, mine)
        shown = [bytes(rng.choice(b"abc ") for _ in range(rng.randrange(1, 200))) for _ in mine]
        grid = np.frombuffer(b"".join(s.ljust(200, b"\0") for s in shown), dtype=np.uint8).reshape(-1, 200)
        best, end = decontam.distances(masks, items.sizes[mine], np.array([place[k] for k in mine]), grid)
        for k, s, d, e in zip(mine, shown, best, end, strict=True):
            got = decontam.within(texts[k], s, 10**6)
            assert got[0] == d and (d == len(texts[k]) or got[1] == e)


def test_items_of_any_size_are_found(spark):
    rng = random.Random(7)
    word = lambda: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randrange(2, 9)))
    long = " ".join(word() for _ in range(2000))
    cjk = "".join(chr(rng.randrange(0x4E00, 0x9000)) for _ in range(120))
    rows = [(1, "c4t"), (2, "a short item of words"), (3, long), (4, cjk), (5, "?!"), (6, None), (None, "null id item"), (2, "a short item of words"), (7, "der " * 40)]
    bench = spark.createDataFrame(rows, "item_id bigint, text string")
    texts = ["a c4t sat", "here is a shart item of words, yes", "x " * 50 + long.replace("e", "o", 300) + " y", "前" * 30 + cjk[:60] + "x" + cjk[61:] + "後", "?! ?!", None, "", "der " * 5000]
    docs = spark.createDataFrame([(i, t, 9, "z") for i, t in enumerate(texts)] + [(None, "a c4t"), (0, "a c4t sat", 9, "z")][1:], "doc_id bigint, text string, item_id int, distance string")
    got = sorted((r.doc_id, r.item_id, r.distance) for r in decontam.contaminated(docs, bench).collect())
    assert [(d, i) for d, i, _ in got] == [(0, 1), (0, 1), (1, 2), (2, 3), (3, 4), (7, 7)]
    assert decontam.clean(docs, bench).columns == docs.columns and {r.doc_id for r in decontam.clean(docs, bench).collect()} == {4, 5, 6}
    assert decontam.clean(docs, bench.limit(0)).count() == docs.count()


def test_long_items_take_bounded_memory():
    rng = np.random.default_rng(2)
    text = bytes(rng.choice(np.frombuffer(b"abcdefghijklmnop    ", np.uint8), 200_000)).decode()
    tracemalloc.start()
    items = decontam.Items([(1, text)])
    assert items.windows(items.bands[0], decontam.normal(text) + b"\0", np.zeros(1, np.int64)).shape[0]
    assert tracemalloc.get_traced_memory()[1] < 200 << 20
    tracemalloc.stop()


def test_registered_query_on_odd_tables(spark, tmp_path):
    docs = spark.createDataFrame([(1, "so the quick brown fox jumped over the lazy dog and went home"), (2, None), (3, "other words")], "doc_id bigint, text string")
    bench = spark.createDataFrame([(5, "The quick brown fox jumps over the lazy dog")], "item_id bigint, text string")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    bench.write.parquet(f"{tmp_path}/benchmark.parquet")
    got = QUERIES["op8_benchmark_decontamination"](spark, str(tmp_path)).collect()
    assert [(r.doc_id, r.item_id, r.distance, r.first_word) for r in got] == [(1, 5, 2, 1)]
