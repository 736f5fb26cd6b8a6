"""Language ID: fit, posterior and letters against plain versions, odd rows, the registered query."""

import itertools
import math

import numpy as np
import pytest

from serieslake.llm import langid
from serieslake.llm.queries import QUERIES

DOCS = "doc_id bigint, text string, lang string, lang_pred int, score string"


@pytest.fixture(scope="module")
def pieces():
    return langid.Pieces(langid.default_vocabulary())


def segmentations(pieces, word):
    full = langid.START + word
    for cuts in itertools.product([0, 1], repeat=len(full) - 1):
        ends = [i + 1 for i, c in enumerate(cuts) if c] + [len(full)]
        parts = [full[a:b] for a, b in zip([0, *ends[:-1]], ends)]
        if all(x in pieces.place for x in parts):
            yield [pieces.place[x] for x in parts]


def test_fit_equals_expectations_over_all_segmentations(pieces):
    counts = {"the": 7, "there": 2, "house": 3, "a": 1}
    n = len(pieces.names)
    probs = np.full(n, 1.0 / n)
    for _ in range(langid.EM_ROUNDS):
        expected = np.full(n + 1, 0.5)
        for word, weight in counts.items():
            each = [(s, math.prod(probs[k] for k in s)) for s in segmentations(pieces, word)]
            total = sum(p for _, p in each)
            for s, p in each:
                for k in s:
                    expected[k] += weight * p / total
        probs = expected[:n] / expected[:n].sum()
    assert np.allclose(pieces.fit([counts])[:n, 0], probs, rtol=1e-9)


def test_long_words_and_long_pieces_are_summed_whole(pieces):
    assert pieces.longest == max(map(len, pieces.names)) > 8
    rng = np.random.default_rng(3)
    probs = rng.random((len(pieces.names) + 1, 2))
    word = "responsibilities" * 6
    sizes, found = pieces.spans([word])
    want = np.log(pieces.forward(sizes, found, probs)[0, -1])
    assert len(word) >= langid.LONG and np.allclose(pieces.word_scores([word, "x"], probs)[0], want)
    short = pieces.fit([{"responsibilities": 6, "the": 2}])
    long = pieces.fit([{"the": 2, word: 1}])
    assert abs(long[pieces.place["ities"], 0] / short[pieces.place["ities"], 0] - 1) < 0.5


@pytest.mark.parametrize(("text", "words"), [("½ ² ① Ⅷ ٣ 12 _", []), ("Été x²y", ["été", "x", "y"]), ("", []), ("日本 ß", ["日本", "ß"])])
def test_letters_are_what_unicode_calls_so(text, words):
    assert langid.words_of(text) == words


def test_score_is_the_posterior(spark, pieces):
    probs = np.vstack([np.random.default_rng(1).random((len(pieces.names), 3)), [[langid.FLOOR] * 3]])
    df = spark.createDataFrame([(1, "the house"), (2, "½"), (3, "tie")], "doc_id bigint, text string")
    got = {r.doc_id: r for r in langid.predict(df, (["a", "b", "c"], probs), langid.default_vocabulary()).collect()}
    each = np.prod([sum(np.prod([probs[k] for k in s], axis=0) for s in segmentations(pieces, w)) for w in ("the", "house")], axis=0)
    assert got[1].lang_pred == "abc"[each.argmax()] and abs(got[1].score - each.max() / each.sum()) < 1e-9
    assert (got[2].lang_pred, got[2].score) == ("und", 0.0)
    even = np.repeat(probs[:, :1], 3, axis=1)
    tie = langid.predict(df, (["a", "b", "c"], even), langid.default_vocabulary()).where("doc_id = 3").first()
    assert tie.lang_pred == "a" and abs(tie.score - 1 / 3) < 1e-9


def test_registered_query(spark, tmp_path):
    english, german = "the house of the king and the people", "der könig und das haus und die leute"
    rows = [(i, (english, german)[i % 2], ("en", "de")[i % 2], 1, "x") for i in range(40)]
    rows += [(100, "½ 12", "en", 0, None), (101, None, None, None, None), (None, english, None, None, None), (102, english, None, None, None), (102, english, None, None, None)]
    spark.createDataFrame(rows, DOCS).write.parquet(f"{tmp_path}/documents.parquet")
    got = QUERIES["op2_language_id"](spark, str(tmp_path)).collect()
    assert len(got) == len(rows) and set(got[0].asDict()) == {"doc_id", "held_out", "lang_pred", "score"}
    by = {r.doc_id: r for r in got}
    assert all(by[i].lang_pred == ("en", "de")[i % 2] for i in range(40))
    assert by[100].lang_pred == by[101].lang_pred == "und" and by[None].lang_pred == by[102].lang_pred == "en"
    import zlib

    assert all(r.held_out == (r.doc_id is not None and zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in got)
