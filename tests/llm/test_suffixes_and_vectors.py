"""Substring dedup and embedding near-duplicates against brute force."""

import hashlib
import random

import numpy as np
import pytest

from serieslake.llm import embeddings, suffixes

DOCS = "doc_id bigint, text string, kept string"


def by_definition(rows):
    first, out = {}, {}
    data = {d: (t or "").encode() for d, t in rows}
    for d in sorted(data):
        for i in range(len(data[d]) - 49):
            first.setdefault(data[d][i : i + 50], d)
    for d, b in data.items():
        gone = [False] * len(b)
        for i in range(len(b) - 49):
            if first[b[i : i + 50]] < d:
                gone[i : i + 50] = [True] * 50
        kept = bytes(x for x, g in zip(b, gone) if not g)
        out[d] = (len(b), sum(gone), sum(g and not p for g, p in zip(gone, [False, *gone])), hashlib.sha256(kept).hexdigest())
    return out


def compare(spark, rows):
    got = suffixes.deduplicate(spark.createDataFrame([(d, t, "x") for d, t in rows], DOCS))
    assert {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got.collect()} == by_definition(rows)


def planted(seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdeé ") for _ in range(rng.randint(1, 9)))
    prose = lambda n: " ".join(word() for _ in range(n))
    shared = [prose(n) for n in (9, 10, 11, 12, 20, 60)]
    rows = []
    for i in range(60):
        parts = [prose(rng.randint(0, 30))]
        for _ in range(rng.randint(0, 3)):
            s = rng.choice(shared)
            a = rng.randint(0, len(s) // 2)
            parts += [s[a : a + rng.randint(30, len(s))], prose(rng.randint(0, 10))]
        rows.append((i * 3 % 61, "".join(parts)))
    rows += [(100, None), (101, ""), (102, "a" * 300), (103, "b" + "a" * 120), (104, "ab" * 200), (105, "x" * 49), (106, "x" * 50), (107, "x" * 51), (-5, shared[5])]
    rows += [(200 + i, rows[i][1]) for i in range(5)]
    return rows


@pytest.mark.parametrize("seed", [1, 2])
def test_removed_bytes_equal_brute_force(spark, seed, monkeypatch):
    monkeypatch.setattr(suffixes, "CENSUS_BYTES", 4000)
    monkeypatch.setattr(suffixes, "SUFFIX_BYTES", 3000)
    monkeypatch.setattr(suffixes, "BLOCK_BYTES", 5000)
    compare(spark, planted(seed))


def test_hot_grams_are_shared_out(spark, monkeypatch):
    monkeypatch.setattr(suffixes, "SUFFIX_BYTES", 1500)
    rng = random.Random(8)
    word = lambda: "".join(rng.choice("abcde ") for _ in range(rng.randint(1, 30)))
    hot = "this line stands in very many documents"
    rows = [(i, rng.choice(["", word(), "same before "]) + hot + rng.choice(["", word(), " same after and more of it"])) for i in range(150)]
    df = spark.createDataFrame([(d, t, "x") for d, t in rows], DOCS)
    assert suffixes.splitters(df, 150, 12)[1]
    compare(spark, rows)


def test_documents_of_the_small_tables(spark, sf):
    compare(spark, [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()])


def test_long_documents_are_read_in_pieces(monkeypatch):
    rng = random.Random(9)
    texts = [bytes(rng.choice(b"abcd") for _ in range(n)) for n in (0, 10, 60, 5000, 300, 2500)]
    whole = {(int(a), int(b)) for a, b, _ in zip(*suffixes.anchored(suffixes.Hasher(), texts))}
    monkeypatch.setattr(suffixes, "PIECE", 700)
    parts = {(int(a), int(b)) for a, b, _ in zip(*suffixes.anchored(suffixes.Hasher(), texts))}
    assert parts == whole


def test_multikey_sort():
    rng = np.random.default_rng(0)
    w = rng.integers(0, 3, size=(500, 4)).astype(np.uint64)
    got = w[suffixes.multikey_sort(w)]
    assert [tuple(x) for x in got] == sorted(tuple(x) for x in w)


def test_empty_and_null_ids(spark):
    df = spark.createDataFrame([], DOCS)
    assert suffixes.deduplicate(df).count() == 0
    df = spark.createDataFrame([(None, "z" * 80, None), (1, "z" * 80, None), (1, "z" * 80, None)], DOCS)
    assert sorted((r.n_bytes, r.n_removed) for r in suffixes.deduplicate(df).collect()) == [(80, 0)] * 3


def vectors(spark):
    rng = np.random.default_rng(4)
    rows = []
    for i in range(60):
        c = rng.standard_normal(16)
        for j in range(rng.integers(1, 6)):
            v = c / np.linalg.norm(c) + rng.standard_normal(16) * rng.choice([0, 0.02, 0.04, 0.06])
            rows.append((len(rows), [float(x) for x in v * rng.uniform(0.5, 2)], int(i % 3)))
    rows += [(len(rows) + k, list(rows[0][1]), rows[0][2]) for k in range(4)]
    n = len(rows)
    rows += [(n, None, 1), (n + 1, [0.0] * 16, 1), (n + 2, [float("nan")] * 16, 1), (n + 3, [1.0, None], 1), (n + 4, list(rows[0][1]), None), (n + 5, [], 1), (n + 6, [float("inf")] * 16, 0), (n + 7, [1.0, 2.0], 1), (None, list(rows[0][1]), 0)]
    return spark.createDataFrame(rows, "vec_id bigint, embedding array<double>, label int"), rows


@pytest.mark.parametrize("block", [2048, 6])
def test_embedding_links_equal_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(embeddings, "BLOCK", block)
    df, rows = vectors(spark)
    rng = np.random.default_rng(9)
    dense = rng.standard_normal(16)
    more = [(1000 + k, [float(x) for x in dense / np.linalg.norm(dense) + rng.standard_normal(16) * 0.02], 1) for k in range(70)]
    df, rows = df.unionByName(spark.createDataFrame(more, df.schema)), rows + more
    ok = [r for r in rows if r[0] is not None and r[1] and r[2] is not None and all(x is not None and np.isfinite(x) for x in r[1]) and any(r[1])]
    near = {r[0]: set() for r in rows if r[0] is not None}
    for a in ok:
        for b in ok:
            if a[0] != b[0] and a[2] == b[2] and len(a[1]) == len(b[1]):
                x, y = np.array(a[1]), np.array(b[1])
                if x @ y / np.linalg.norm(x) / np.linalg.norm(y) >= 0.98:
                    near[a[0]].add(b[0])
    root = {v: v for v in near}
    for _ in range(len(near)):
        root = {v: min([root[v], *(root[w] for w in near[v])]) for v in near}
    got = {r.vec_id: r for r in embeddings.near_duplicates(df).collect()}
    assert len(got) == len(rows)
    for v in near:
        assert (got[v].n_links, got[v].component_id, got[v].kept) == (len(near[v]), root[v], root[v] == v)
    assert (got[None].n_links, got[None].component_id, got[None].kept) == (0, None, False)
    assert embeddings.near_duplicates(df.limit(0)).count() == 0


def test_cells_hold_few_unrelated_pairs_at_any_size():
    for n in (100, 10_000, 10**6, 10**9):
        width, count = embeddings.bands(n)
        apart, linked = embeddings.same_cell(1 / 0.2 * 2**0.5), embeddings.same_cell(1.0)
        assert n * apart**width <= embeddings.CROWD and (1 - linked**width) ** count <= 1 - embeddings.RECALL
    assert embeddings.bands(10**9)[1] < 40 * embeddings.bands(100)[1]


def test_pairs_of_groups():
    got = [(int(x), int(y)) for a, b in embeddings.pairs_of(np.array([3, 1, 2, 4])) for x, y in zip(a, b)]
    assert got == [(0, 1), (0, 2), (1, 2), (4, 5), (6, 7), (6, 8), (6, 9), (7, 8), (7, 9), (8, 9)]
