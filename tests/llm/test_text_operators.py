"""BPE, chat, HTML, PII and SimHash against brute force, libraries and round trips."""

import random
import re

import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from serieslake.llm import chat, html, pii, simhash
from serieslake.llm.common import components

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"
ODD = ["", "   ", None, "a", "  a　b  ", "x<|endoftext|>y", "\x1c\x85 ½ é é \U0001f600", "it's   we'll\n\n 12 ٣", "the " * 3000]


def docs(spark, texts):
    return spark.createDataFrame([(i, t, None, None, None) for i, t in enumerate(texts)], DOCS)


def test_chat_round_trip_and_loss(spark):
    rows = [(1, 0, "system", "rules"), (1, 1, "user", r"\### assistant: </turn>"), (1, 2, "assistant", r"\### Assistant: </turn> ok"), (2, 0, "assistant", None), (3, 0, None, " "), (None, 1, "user", "x"), (2, 1, "assistant", "1"), (2, 2, "assistant", " </turn>\n")]
    rows += [(9, i, "assistant" if i % 2 else "user", f"1 say {i} \\") for i in range(130)]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")
    got = {r.conv_id: r for r in chat.render(df).collect()}
    for conv, r in got.items():
        mine = sorted((t, ro or "", tx or "") for c, t, ro, tx in rows if c == conv)
        assert chat.read_turns(r.formatted) == [(ro, tx) for _, ro, tx in mine]
        cuts = [chat.unescape(r.formatted[a:b]) for a, b in zip(r.loss_spans[::2], r.loss_spans[1::2])]
        assert cuts == [tx for _, ro, tx in mine if ro == "assistant"]
        assert not r.rewritten


def test_chat_sees_a_rewrite_at_any_turn():
    def once(turns):
        return ("<" if len(turns) == 10 else "(") + "".join(f"{r}:{t}\n" for r, t in turns)

    for n in (9, 10, 48, 49, 130):
        assert chat.Rendered([("user", f"t{i}") for i in range(n)], once).rewritten == (n >= 10)


def test_chat_on_odd_tables(spark, tmp_path):
    from serieslake.llm.queries import CHAT_EXTRA, QUERIES

    rows = [(1, 0, "user", "hi", 1), (1, 1, "assistant", "a < b", 1), (1, 1, "assistant", "a < b", 1), (None, 0, None, None, None), (2, 0, "assistant", "", 0), *((3, i, "assistant", f"line {i}", 0) for i in range(3000))]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string, n_turns int")
    df.write.parquet(f"{tmp_path}/conversations.parquet")
    got = {r.conv_id: r for r in QUERIES["op10_chat_rendering"](spark, str(tmp_path)).collect()}
    assert {k: (r.n_turns, r.loss_chars) for k, r in got.items()} == {1: (3, 10), None: (1, 0), 2: (1, 0), 3: (3000, sum(len(f"line {i}") for i in range(3000))), -7: (2, len(CHAT_EXTRA))}
    assert chat.render(df.limit(0)).count() == 0


def test_chat_sees_rewritten_history():
    def numbered(turns):
        return f"{len(turns)} turns\n" + "".join(f"<{r}>{t}</{r}>" for r, t in turns)

    got = chat.Rendered([("user", "a"), ("assistant", "b")], numbered)
    assert got.rewritten
    assert [got.text[a:b] for a, b in got.texts[1:]] == ["b"]


PAGE = """<html><body><nav><ul><li><a href=x>Home</a></ul></nav><div class="ad">Buy, now, this</div>
<div id=wrap><article><h1>A &amp; B</h1><p><b>First  paragraph, with &lt;signs&gt;.<br><p>Second one is rather longer, it has commas, and words enough.</p>
<aside>other</aside><div class="comments"><p>I think, that, this, is, a, long comment, by a reader, really.</p></div></article></div>
<script>var t="</p>";</script><footer>&copy; us</footer>"""


def test_html_main_text(spark):
    assert html.main_text(PAGE) == "A & B\nFirst paragraph, with <signs>.\nSecond one is rather longer, it has commas, and words enough."
    assert [html.main_text(x) for x in (None, "", "<p>", "<script>x")] == ["", "", "", ""]
    assert html.main_text("plain") == "plain"
    df = spark.createDataFrame([(1, "u", PAGE, "x"), (None, None, None, None)], "page_id bigint, url string, html string, text string")
    assert {(r.page_id, r.n_chars) for r in html.extract(df).collect()} == {(1, len(html.main_text(PAGE))), (None, 0)}


def test_html_gives_back_the_article_of_given_pages(spark, sf):
    for r in spark.read.parquet(f"{sf}/pages.parquet").collect():
        art = re.search(r"<article>(.*)</article>", r.html, re.S)[1]
        lines = [" ".join(x.split()) for x in html.unescape(re.sub(r"<b>", "", re.sub(r"</?(?:p|h1|br)>", "\0", art))).split("\0")]
        assert html.main_text(r.html) == "\n".join(x for x in lines if x)


def spans_by_regex(text):
    out = []
    for k, p in enumerate((r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([\x20-]?[0-9])+", r"\+[0-9][\x20().0-9-]+[0-9]")):
        for m in re.finditer(p, text):
            digits = re.sub("[^0-9]", "", m[0])
            ok = (True, k == 1 and all(int(x) <= 255 for x in m[0].split(".")), 12 <= len(digits) <= 19 and pii.luhn(digits), 9 <= len(digits) <= 15)[k]
            if ok:
                out.append((m.start(), k, m.end()))
    return [(s, pii.KINDS[k], e) for s, k, e in sorted(out)]


@settings(max_examples=400, deadline=None)
@given(st.text(alphabet="ab.@-+ 0147()%é\n", max_size=50))
def test_pii_base_spans_equal_the_shapes(text):
    assert pii.base_spans(text) == spans_by_regex(text)


def test_pii_base_on_documents(spark, sf):
    for r in spark.read.parquet(f"{sf}/documents.parquet").collect():
        assert pii.base_spans(r.text) == spans_by_regex(r.text)


def test_pii_contexts_find_unseen_identifiers(spark):
    texts = [f"please call my number +1 (555) 010-{i:04d} today" for i in range(12)] + ["please call my number 0049-ABC-77123 today", "nothing 12 here", None, "please call my number 0049-ABC-77123 today"]
    got = {r.doc_id: r for r in pii.detect(docs(spark, texts)).collect()}
    assert got[12].base == "" and got[12].spans == "phone:22:36" and got[15].spans == "phone:22:36"
    assert got[0].spans == got[0].base == "phone:22:39"
    assert got[13].spans == got[14].spans == ""
    red = {r.doc_id: r.text for r in pii.redact(docs(spark, texts)).collect()}
    assert red[0] == "please call my number <PHONE> today" and red[13] == texts[13] and red[14] is None
    assert len(red) == len(texts)
    assert pii.detect(docs(spark, [])).count() == 0


def test_pii_instances_meet_the_stated_rule():
    def found(t):
        return [t[s:e] for s, e in pii.instances(t)]

    assert found("badge K4J9X2P7. then jane.doe(at)example.org!") == ["K4J9X2P7", "jane.doe(at)example.org"]
    assert found("ring 555 123 4567 or (555) 123 4567, state-of-the-art wonderful.") == ["555 123 4567", "(555) 123 4567"]
    assert found("0049-ABC-77123 555 123 4567x and 1 2 3 4") == ["0049-ABC-77123"]
    assert [r["value"] for r in pii.entities("mail a.b@c.org or K4J9X2P7")[1]] == ["a.b@c.org", "K4J9X2P7"]


def test_pii_accepted_instances_are_seeds(spark):
    codes = [f"K{i}J9X2P7" for i in range(6)]
    texts = [f"please call my number +1 (555) 010-{i:04d} today" for i in range(12)]
    texts += [f"please call my number {c} today" for c in codes] + [f"her new badge code {c} expires" for c in codes]
    texts += ["her new badge code 0049-XYZ-9 expires", "some other place 0049-XYZ-9 here"]
    got = {r.doc_id: r.spans for r in pii.detect(docs(spark, texts)).collect()}
    assert got[12] == "phone:22:30" and got[24] == "phone:19:29" and got[25] == ""


def test_pii_obfuscated_mail_after_a_confident_pattern(spark):
    texts = [f"write me mail to user{i}@example.org soon" for i in range(12)] + ["write me mail to jane.doe(at)example.org soon"]
    got = {r.doc_id: r.spans for r in pii.detect(docs(spark, texts)).collect()}
    assert got[12] == "email:17:40"


def fp_by_definition(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))]
    hs = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def test_simhash_fingerprints(spark, sf):
    texts = ODD + ["One two", "A B C D", "a b c d e é"] + [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").limit(30).collect()]
    for t in texts:
        assert simhash.fingerprint(t) == fp_by_definition(t)


def test_simhash_groups_equal_brute_force(spark):
    rng = random.Random(3)
    fps = [rng.getrandbits(64) for _ in range(120)]
    for _ in range(500):
        f = rng.choice(fps)
        for b in rng.sample(range(64), rng.choice([1, 2, 3, 4, 5, 6])):
            f ^= 1 << b
        fps.append(f)
    v = np.array(fps, dtype=np.uint64)
    df = spark.createDataFrame([(int(x), int(x)) for x in np.unique(v).view(np.int64)], "fp bigint, rep bigint")
    got = {r.node: r.root for r in components(simhash.links(df)).collect()}
    u = np.unique(v)
    near = np.bitwise_count(u[:, None] ^ u[None]) <= 4
    root = np.arange(len(u))
    for _ in range(200):
        root = np.array([root[near[i]].min() for i in range(len(u))])
    for members in (np.flatnonzero(root == r) for r in set(root)):
        names = {got.get(int(x), int(x)) for x in u[members].view(np.int64)}
        assert len(names) == 1


@pytest.mark.parametrize("texts", [[], ["a b c d e f", "a b c d e f", None, "", "x y"]])
def test_simhash_odd_rows(spark, texts):
    df = docs(spark, texts).unionByName(spark.createDataFrame([(None, "a b c d e f", None, None, None)], DOCS))
    got = simhash.groups(df).orderBy("doc_id").collect()
    assert len(got) == len(texts) + 1
    if texts:
        assert [r.component_id for r in got] == [None, 0, 0, 2, 2, 4]


def test_components_of_a_long_chain(spark):
    edges = spark.range(200).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    assert {r.root for r in components(edges).collect()} == {0}
