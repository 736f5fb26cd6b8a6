"""The pipeline against a brute-force version, and on odd rows."""

import numpy as np
from pyspark.sql import functions as F

import corpus_pipeline
from serieslake.llm import bpe, decontam, langid, pii, simhash


def by_hand(rows, items):
    """doc_id -> text as it reaches the last stage."""
    left = {d: t for d, t in rows if t and langid.LETTERS.search(t)}
    ids = sorted(left)
    fps = np.array([simhash.fingerprint(left[d]) for d in ids], dtype=np.uint64)
    near = np.bitwise_count(fps[:, None] ^ fps[None]) <= 4
    root = np.arange(len(ids))
    for _ in range(len(ids)):
        new = np.array([root[near[i]].min() for i in range(len(ids))])
        if (new == root).all():
            break
        root = new
    left = {ids[i]: left[ids[i]] for i in range(len(ids)) if root[i] == i}
    norm = [decontam.normal(t) for t in items]
    dirty = {d for d, t in left.items() if any(decontam.within(j, decontam.normal(t), int(decontam.DISTANCE * len(j))) for j in norm)}
    out = {}
    for d, t in left.items():
        if d not in dirty:
            for s, k, e in reversed(pii.base_spans(t)):
                t = t[:s] + f"<{k.upper()}>" + t[e:]
            out[d] = t
    return out


def test_run_equals_a_brute_force_version(spark, sf):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(bpe.default_vocabulary())
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    want = by_hand(rows, [r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()])
    got = {r.doc_id: r.ids for r in corpus_pipeline.run(spark, sf).collect()}
    assert set(got) == set(want)
    for d, ids in got.items():
        assert ids == tok.encode(want[d], add_special_tokens=False).ids


def test_stages_keep_columns_and_stand_odd_rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(40)
    odd = spark.createDataFrame([(None, None, None, None, None), (900, None, "en", None, 1), (901, "", None, "s", None), (902, "12 34", None, None, None), (903, "b " * 4000, None, None, None), (903, "b " * 4000, None, None, None), (None, "a word", None, None, None)], docs.schema)
    df = docs.unionByName(odd).withColumns({n: F.lit(1) for n in ("lang_pred", "score", "fp", "spans", "d", "k")})
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, df, sf)
        if name != "bpe":
            assert out.columns == df.columns
        n = out.count()
        assert 0 < n <= df.count()
        assert stage(spark, df.limit(0), sf).count() == 0
    left = {(r.doc_id, r.text) for r in corpus_pipeline.identify_language(spark, df, sf).collect()}
    assert (900, None) not in left and (902, "12 34") not in left and (None, "a word") in left
    assert corpus_pipeline.drop_near_duplicates(spark, df, sf).where("doc_id = 903").count() == 1
