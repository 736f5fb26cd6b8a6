"""Language ID, decontamination and language-model scoring against brute force, planted cases and held-out rows."""

import itertools
import math
import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from serieslake.llm import decontam, langid, lm
from serieslake.llm.common import cut
from serieslake.llm.queries import QUERIES

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def docs(spark, rows):
    return spark.createDataFrame([(i, t, lang, None, None) for i, (t, lang) in enumerate(rows)], DOCS)


def test_forward_sum_equals_all_segmentations():
    p = langid.Pieces(langid.default_vocabulary())
    rng = np.random.default_rng(1)
    probs = np.vstack([rng.random((len(p.names), 2)), [[langid.FLOOR] * 2]])
    index = {n: i for i, n in enumerate(p.names)}
    for word in ("the", "ation", "été", "x"):
        full = langid.START + word
        want = np.zeros(2)
        for cuts in itertools.product([0, 1], repeat=len(full) - 1):
            ends = [i + 1 for i, c in enumerate(cuts) if c] + [len(full)]
            parts = [full[a:b] for a, b in zip([0, *ends[:-1]], ends)]
            if all(x in index for x in parts):
                want += np.prod([probs[index[x]] for x in parts], axis=0)
        assert np.allclose(np.exp(p.word_scores([word], probs)[0]), want)


def test_language_id_held_out_accuracy_and_odd_rows(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet")
    got = langid.identify(d, keep=("doc_id", "lang")).withColumn("h", langid.held_out()).where("h").collect()
    assert sum(r.lang == r.lang_pred for r in got) / len(got) > 0.97
    odd = docs(spark, [(None, "en"), ("123 !", "en"), ("the and of " * 2000, None), ("hello the", "en"), ("der die und", "de"), ("x" * 500, None)])
    r = {x.doc_id: x for x in langid.identify(odd).collect()}
    assert (r[0].lang_pred, r[1].lang_pred, r[0].score) == ("und", "und", 0.0)
    assert len(r) == 6 and r[2].lang_pred in ("en", "de")
    assert langid.identify(docs(spark, [])).count() == 0


def edit(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        prev, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            prev, row[j] = row[j], min(prev + (x != y), row[j] + 1, row[j - 1] + 1)
    return row[-1]


def test_exact_edit_distance():
    rng = random.Random(2)
    for _ in range(60):
        a = bytes(rng.choice(b"abc") for _ in range(rng.randint(1, 9)))
        t = bytes(rng.choice(b"abc") for _ in range(rng.randint(0, 14)))
        want = min(edit(a, t[i:j]) for i in range(len(t) + 1) for j in range(i, len(t) + 1))
        assert decontam.within(a, t, 99)[0] == want


def test_planted_passages_are_found_and_clean_ones_left(spark, sf):
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    items = bench.collect()
    rng = random.Random(5)
    plain = [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").limit(60).collect()]
    rows, want = [], set()
    for i, t in enumerate(plain):
        if i % 2:
            item = items[i % len(items)]
            words = item.text.split()
            for _ in range(len(words) // 12 if i % 4 == 1 else 0):  # a word in twelve is changed, dropped or doubled
                k = rng.randrange(len(words))
                words[k : k + 1] = rng.choice([["zzz"], [], [words[k]] * 2])
            at = rng.randrange(len(t.split()) + 1)
            t = " ".join([*t.split()[:at], *words, *t.split()[at:]])
            want.add((i, item.item_id))
        rows.append((t, "en"))
    df = docs(spark, [*rows, (None, None), ("", None)])
    got = {(r.doc_id, r.item_id) for r in decontam.contaminated(df, bench).collect()}
    assert want <= got
    texts = {i: decontam.normal(t) for i, (t, _) in enumerate(rows)}
    for d, i in got - want:  # what else is found is there
        j = decontam.normal(next(x.text for x in items if x.item_id == i))
        assert decontam.within(j, texts[d], int(decontam.DISTANCE * len(j)))
    left = {r.doc_id for r in decontam.clean(df, bench).collect()}
    assert left == set(range(len(rows) + 2)) - {d for d, _ in got}
    assert decontam.contaminated(df, bench.limit(0)).count() == 0


def by_hand(rows, good):
    """(target loss, background loss) of each text, straight from the formulas."""
    said = {i: (t or "").lower().split() for i, t in enumerate(rows)}
    vocabulary = {w for ws in said.values() for w in ws}
    total = sum(len(ws) for i, ws in said.items() if i in good)

    def model(ids, scale):
        pair, single = Counter(), Counter()
        for i in ids:
            single[None] += bool(said[i])
            single.update(said[i])
            pair.update(zip([None, *said[i]], said[i]))
        return lambda v, w: -math.log2((scale * pair[v, w] + lm.PRIOR * (scale * single[w] + 1) / (total + len(vocabulary))) / (scale * single[v] + lm.PRIOR))

    every = sum(map(len, said.values()))
    models = model(good, 1), model(said, total / every if every else 0)
    return {i: [sum(m(v, w) for v, w in zip([None, *ws], ws)) / len(ws) for m in models] for i, ws in said.items() if ws}


@pytest.mark.parametrize("size", [1 << 22, 40])
def test_cross_entropy_difference_equals_a_plain_computation(spark, monkeypatch, size):
    monkeypatch.setattr(lm, "UNIT_TOKENS", size)
    monkeypatch.setattr(lm, "BUCKET_BYTES", 300)
    rng = random.Random(6)
    rows = ["a b a b c", "b a b", None, "", "c c zzzebra", "  \n", *(" ".join(rng.choice("abcdefghij") * rng.randrange(1, 4) for _ in range(rng.randrange(40))) for _ in range(80)), "the hot line " * 300, "the hot line " * 300]
    good = {1, 2, 3, 20, 21, 22, 86}
    df = spark.createDataFrame([(i, t, 0, "x") for i, t in enumerate(rows)], "doc_id bigint, text string, score int, ids string").repartition(5)
    labels = spark.createDataFrame([(i,) for i in good] + [(1,), (None,), (999,)], "doc_id bigint")
    want = by_hand(rows, good)
    for limit in (1 << 20, 1):
        monkeypatch.setattr(lm, "BROADCAST_IDS", limit)
        got = {r.doc_id: r for r in lm.score(df, labels).collect()}
        assert len(got) == len(rows)
        for i, t in enumerate(rows):
            assert got[i].n_tokens == len((t or "").split())
            if i in want:
                assert abs(got[i].target_loss - want[i][0]) < 1e-9 and abs(got[i].background_loss - want[i][1]) < 1e-9 and abs(got[i].score - (want[i][0] - want[i][1])) < 1e-9
            else:
                assert got[i].score is None and got[i].target_loss is None


def test_scores_on_odd_tables(spark, tmp_path):
    rows = [(None, "a b"), (1, None), (2, "a b a"), (2, "a b a"), (3, "x")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    df.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(2, 1, 0), (2, 0, 0), (3, None, 0), (None, 1, 0)], "doc_id bigint, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    got = QUERIES["op9_cross_entropy_difference"](spark, str(tmp_path)).collect()
    assert len(got) == 5 and {r.doc_id: r.n_tokens for r in got} == {None: 2, 1: 0, 2: 3, 3: 1}
    scores = {r.doc_id: r.score for r in got}
    assert scores[2] < scores[3] and scores[1] is None and scores[None] is not None
    none = spark.createDataFrame([], "doc_id bigint")
    assert {r.score for r in lm.score(df, none).collect()} == {0.0, None}
    assert lm.score(df.limit(0), none).count() == 0


def test_documents_that_occur_twice_are_scored_apart(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet").where("length(text) > 2000").select("doc_id", "text").limit(100)
    twice = d.where("doc_id % 5 = 0")
    both = cut(d.unionByName(twice.withColumn("doc_id", F.col("doc_id") + 10**6)))
    s = lm.score(both, d.where("doc_id % 7 = 3")).where("doc_id < 1000000 and doc_id % 7 <> 3").groupBy((F.col("doc_id") % 5 == 0).alias("two")).agg(F.avg("background_loss").alias("b")).collect()
    m = {r.two: r.b for r in s}
    assert m[True] < m[False]


def test_good_documents_score_lower(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet").where("lang = 'en'")
    good = spark.read.parquet(f"{sf}/documents.parquet").where("lang = 'de'")
    both = d.unionByName(good)
    s = lm.score(both, good).join(both.select("doc_id", "lang"), "doc_id").groupBy("lang").agg(F.avg("score").alias("s")).collect()
    m = {r.lang: r.s for r in s}
    assert m["de"] < m["en"]
