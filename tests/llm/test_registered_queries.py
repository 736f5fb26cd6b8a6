"""The registered queries over odd tables of documents and vectors, against plain computations."""

import hashlib
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from serieslake.llm.queries import QUERIES
from test_suffixes_and_vectors import by_definition
from test_text_operators import fp_by_definition, spans_by_regex

CLASHES = ("fp", "rep", "base", "spans", "n_email", "d", "k", "bucket", "unit", "n_bytes", "component_id")


def texts():
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 8)))
    prose = lambda n: " ".join(word() for _ in range(n))
    shared = prose(30)
    out = [None, "", "  \n", "x", shared, f"{prose(5)} {shared} {prose(5)}", shared + " end", "long " * 60_000]
    out += ["mail a.b@c.org or 10.0.0.1, card 4111 1111 1111 1111, call +1 (555) 010-0199", "é" * 200, prose(400), prose(3)]
    return out + out[4:7]


@pytest.fixture(scope="module")
def odd(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("odd"))
    rows = [(i * 7 % 101, t) for i, t in enumerate(texts())]
    df = spark.createDataFrame(rows, "doc_id bigint, text string").withColumns({c: F.lit("clash") for c in CLASHES})
    df.write.parquet(f"{folder}/documents.parquet")
    return folder, dict(rows)


@pytest.fixture(scope="module")
def none(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("none"))
    spark.createDataFrame([], "doc_id bigint, text string").write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([], "vec_id bigint, embedding array<float>, label int").write.parquet(f"{folder}/embeddings.parquet")
    return folder


def test_suffix_array_dedup(spark, odd):
    folder, rows = odd
    got = QUERIES["op3_suffix_array_dedup"](spark, folder).collect()
    assert {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got} == by_definition(list(rows.items()))


def test_simhash_groups(spark, odd):
    folder, rows = odd
    fps = {d: fp_by_definition(t) for d, t in rows.items()}
    root = {d: d for d in fps}
    for _ in fps:
        root = {a: min(root[b] for b in fps if (fps[a] ^ fps[b]).bit_count() <= 4) for a in fps}
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in QUERIES["op4_simhash_groups"](spark, folder).collect()}
    assert got == {d: (f"{fps[d]:016x}", root[d]) for d in fps}


def test_personal_data(spark, odd):
    folder, rows = odd
    got = {r.doc_id: r for r in QUERIES["op6_pii_bootstrapped"](spark, folder).collect()}
    assert set(got) == set(rows)
    for d, t in rows.items():
        base = spans_by_regex(t or "")
        said = [f"{k}:{s}:{e}" for s, k, e in base]
        r = got[d]
        assert r.base_sha256 == hashlib.sha256(",".join(said).encode()).hexdigest()
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(sum(k == kind for _, k, _ in base) for kind in ("email", "ip", "card", "phone"))
        assert set(said) <= set(r.spans.split(",")) | {""}
    assert sum(r.n_email + r.n_ip + r.n_card + r.n_phone for r in got.values()) >= 4


def test_embeddings(spark, tmp_path):
    rng = np.random.default_rng(2)
    a = rng.standard_normal(8)
    rows = [(1, a, 0), (2, 2 * a, 0), (3, a, 1), (4, a, None), (5, None, 0), (6, -a, 0), (7, a + 0.01, 0), (8, 0 * a, 0)]
    df = spark.createDataFrame([(i, None if v is None else [float(x) for x in v], y, 0) for i, v, y in rows], "vec_id bigint, embedding array<double>, label int, n_links int")
    df.write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in QUERIES["op7_embedding_near_duplicates"](spark, str(tmp_path)).collect()}
    assert got == {1: (2, 1, True), 2: (2, 1, False), 7: (2, 1, False)} | {i: (0, i, True) for i in (3, 4, 5, 6, 8)}


@pytest.mark.parametrize("name", ["op3_suffix_array_dedup", "op4_simhash_groups", "op5_bpe_round_trip", "op6_pii_bootstrapped", "op7_embedding_near_duplicates"])
def test_empty_tables(spark, none, name):
    assert QUERIES[name](spark, none).count() == 0
