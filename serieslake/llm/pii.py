"""Personal data by bootstrapped contextual extraction.

Emails, addresses, cards and phones found by shape are the seeds. Words before and after an
entity are its patterns. Other identifier-like words are unlabelled instances. On the bipartite
graph of patterns and instances Spark repeats: a pattern's confidence is the mean confidence of
its instances, an unlabelled instance's confidence is one minus the chance that all of its
patterns are wrong. Patterns that stay above ``CONFIDENT`` with enough different seeds label the
unlabelled instances they surround; these are seeds of the next pass, until a pass adds no pattern.
An instance is a word that may be an identifier or a number written in groups. Ordinary words are
none, whatever surrounds them. All counts cover all documents; nothing is sampled.

Null text is empty text. Repeated rows give repeated results, an empty table gives no rows, a
null doc_id is kept; other columns are ignored. Spans are code points, end exclusive.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import apart, cut, map_batches

KINDS = ("email", "ip", "card", "phone")
#: The contract's shapes; a run of digits is entered at its first digit only, which finds the same matches in linear time.
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
IP = re.compile(r"(?<![0-9])[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
#: A word that may be an identifier: eight signs or more, with three digits or more, or with three signs of an address or more inside.
WORD = re.compile(r"[^\s\"'<>|,;]{8,}")
DIGIT, ADDRESS = re.compile(r"[0-9]"), re.compile(r"[().\[\]{}@_+]")
#: A number in groups: whole words of digits and few other signs, 7 to 19 digits in all.
GROUPS = re.compile(r"(?<![^\s\"'<>|,;])[+(]?[0-9]+(?:[\x20./()-]{1,2}[0-9]+)+(?![^\s\"'<>|,;.:!?])")
CONFIDENT, SEEDS, SETTLED = 0.8, 5, 1e-3
SPAN = T.ArrayType(T.StructType([T.StructField("kind", T.StringType()), T.StructField("start", T.LongType()), T.StructField("end", T.LongType()), T.StructField("value", T.StringType()), T.StructField("patterns", T.ArrayType(T.StringType()))]))


def emails(text: str):
    end = 0
    at = text.find("@")
    while at >= 0:
        if at >= end:
            start = at
            while start > end and text[start - 1] in LOCAL:
                start -= 1
            if start < at and (m := DOMAIN.match(text, at + 1)):
                end = m.end()
                yield start, end
        at = text.find("@", at + 1)


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[int, str, int]]:
    """(start, kind, end) in order of start, then kind as listed."""
    found = [(s, 0, e) for s, e in emails(text)] if "@" in text else []
    if any(map(text.__contains__, "0123456789")):
        found += [(m.start(), 1, m.end()) for m in IP.finditer(text) if all(len(p := q.lstrip("0")) <= 3 and int(p or 0) <= 255 for q in m.group().split("."))]
        for m in CARD.finditer(text):
            if m.end() - m.start() >= 12:
                digits = m.group().replace(" ", "").replace("-", "")
                if 12 <= len(digits) <= 19 and luhn(digits):
                    found.append((m.start(), 2, m.end()))
        if "+" in text:
            for m in PHONE.finditer(text):
                if 9 <= sum(c in "0123456789" for c in m.group()) <= 15:
                    found.append((m.start(), 3, m.end()))
    return [(s, KINDS[k], e) for s, k, e in sorted(found)]


def _patterns(text: str, start: int, end: int) -> list[str]:
    left = re.findall(r"[^\W\d_]+", text[max(0, start - 60) : start].lower())[-2:]
    right = re.findall(r"[^\W\d_]+", text[end : end + 40].lower())[:1]
    out = []
    if len(left) == 2:
        out.append(f"{left[0]} {left[1]} _")
    if left and right:
        out.append(f"{left[-1]} _ {right[0]}")
    return out


def instances(text: str) -> list[tuple[int, int]]:
    """(start, end) of words and grouped numbers that may be identifiers, in order and apart from each other."""
    groups = []
    if DIGIT.search(text):
        groups = [m.span() for m in GROUPS.finditer(text) if " " in m.group() and 7 <= len(DIGIT.findall(m.group())) <= 19]
    out, k = [], 0
    for m in WORD.finditer(text):
        w = m.group()
        if w.isalpha() or w[:-1].isalpha() or len(DIGIT.findall(w)) < 3 and len(ADDRESS.findall(w[1:-1])) < 3:
            continue
        s, e = m.start(), m.end() - (w[-1] in ".:!?")
        while k < len(groups) and groups[k][1] <= s:
            k += 1
        if k == len(groups) or e <= groups[k][0]:
            out.append((s, e))
    return sorted(out + groups)


def entities(text: str | None) -> tuple[list[tuple[int, str, int]], list[dict]]:
    """Base spans; then these and the unlabelled instances (kind null) with the patterns around them."""
    if not text:
        return [], []
    base = base_spans(text)
    rows = [{"kind": k, "start": s, "end": e, "value": text[s:e], "patterns": _patterns(text, s, e)} for s, k, e in base]
    taken = 0  # base spans that end before the instance
    for s, e in instances(text):
        while taken < len(base) and base[taken][2] <= s:
            taken += 1
        k = taken
        while k < len(base) and base[k][0] < e and base[k][2] <= s:
            k += 1
        if k == len(base) or base[k][0] >= e:
            rows.append({"kind": None, "start": s, "end": e, "value": text[s:e], "patterns": _patterns(text, s, e)})
    return base, rows


def joined(spans) -> str:
    return ",".join(f"{k}:{s}:{e}" for s, k, e in spans)


def found(docs: DataFrame) -> DataFrame:
    """doc_id, row key, base spans as text, counts by kind, entities with patterns."""

    def run():
        def work(texts):
            out = [[] for _ in range(6)]
            for t in texts:
                base, rows = entities(t)
                for col, v in zip(out, (joined(base), *(sum(k == kind for _, k, _ in base) for kind in KINDS), rows), strict=True):
                    col.append(v)
            return out

        return work

    fields = [T.StructField("base", T.StringType()), *(T.StructField(f"n_{k}", T.LongType()) for k in KINDS), T.StructField("entities", SPAN)]
    keyed = docs.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("text_key"))
    return map_batches(keyed, ["doc_id", "text_key"], ["text"], fields, run)


def confident_patterns(edges: DataFrame) -> DataFrame:
    """(pattern, kind) from edges (pattern, value, kind or null), scored iteratively."""
    seeds = edges.where("kind is not null").groupBy("pattern", "kind").agg(F.countDistinct("value").alias("n")).groupBy("pattern").agg(F.max_by("kind", F.struct("n", "kind")).alias("p_kind"), F.max("n").alias("n"))
    seeds = cut(seeds.where(F.col("n") >= SEEDS))
    graph = edges.join(seeds.select("pattern", "p_kind"), "pattern").select("pattern", "p_kind", "value", "kind").distinct()
    graph = cut(graph.withColumn("conf", F.when(F.col("kind") == F.col("p_kind"), 1.0).otherwise(0.0)))
    if graph.isEmpty():
        return seeds.select("pattern", F.col("p_kind").alias("kind")).limit(0)
    change = 1.0
    while change > SETTLED:  # confidences only rise and are below one, so this ends
        scores = graph.groupBy("pattern").agg(F.avg("conf").alias("score"))
        instances = graph.where("kind is null").join(scores, "pattern").groupBy("value", "p_kind").agg((1 - F.exp(F.sum(F.log1p(-F.least(F.col("score"), F.lit(0.999)))))).alias("now"))
        new = F.when(F.col("kind").isNull(), F.coalesce("now", F.lit(0.0))).otherwise(F.col("conf"))
        graph = cut(graph.select("pattern", "p_kind", "value", "kind", "conf").join(instances, ["value", "p_kind"], "left").select("pattern", "p_kind", "value", "kind", F.abs(new - F.col("conf")).alias("moved"), new.alias("conf")))
        change = graph.agg(F.max("moved")).first()[0] or 0.0
    return graph.groupBy("pattern", "p_kind").agg(F.avg("conf").alias("score")).where(F.col("score") >= CONFIDENT).select("pattern", F.col("p_kind").alias("kind"))


def bootstrapped(edges: DataFrame) -> DataFrame:
    """(pattern, kind) of all passes: instances that a pass accepts are seeds of the next, until none adds a pattern."""
    edges = cut(edges.distinct())
    good = cut(confident_patterns(edges))
    n = good.count()
    while n:
        accepted = edges.where("kind is null").join(good.select("pattern", F.col("kind").alias("k")), "pattern").groupBy("value").agg(F.min("k").alias("k"))
        known = edges.join(accepted, "value", "left").select("pattern", "value", F.coalesce("kind", "k").alias("kind"))
        good = cut(good.unionByName(confident_patterns(known).join(good, "pattern", "left_anti")))
        before, n = n, good.count()
        if n == before:
            break
    return good


def detect(docs: DataFrame) -> DataFrame:
    """doc_id, text_key, counts, base and all spans (text form) of every row."""
    rows = cut(found(docs))
    ents = rows.where(F.size("entities") > 0).select("doc_id", "text_key", F.explode("entities").alias("e")).select("doc_id", "text_key", "e.*")
    edges = ents.select("doc_id", "text_key", "start", "end", "value", "kind", F.explode("patterns").alias("pattern"))
    good = bootstrapped(edges.select("pattern", "value", "kind")).select(F.col("pattern").alias("good"), F.col("kind").alias("new_kind"))
    new = edges.where("kind is null").join(good, F.col("pattern") == F.col("good")).groupBy(F.col("doc_id").alias("d"), F.col("text_key").alias("k")).agg(F.array_sort(F.collect_set(F.struct("start", "end", "new_kind"))).alias("extra"))
    both = rows.join(new, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("text_key") == F.col("k")), "left")
    place = F.create_map(*(x for i, k in enumerate(KINDS) for x in (F.lit(k), F.lit(i))))
    of_base = F.transform(F.filter(F.split("base", ","), lambda s: s != ""), lambda s: F.struct(F.split(s, ":")[1].cast("long").alias("start"), place[F.split(s, ":")[0]].alias("k"), F.split(s, ":")[2].cast("long").alias("end"), F.split(s, ":")[0].alias("kind")))
    of_new = F.transform(F.coalesce("extra", F.array().cast("array<struct<start:bigint,end:bigint,new_kind:string>>")), lambda s: F.struct(s["start"].alias("start"), place[s["new_kind"]].alias("k"), s["end"].alias("end"), s["new_kind"].alias("kind")))
    spans = F.array_sort(F.concat(of_base, of_new))
    return both.select("doc_id", "text_key", *(f"n_{k}" for k in KINDS), "base", F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",").alias("spans"))


def redact(docs: DataFrame) -> DataFrame:
    """``docs`` with each span of the text replaced by its kind in angle brackets; n_chars follows."""
    found_ = detect(docs).where("spans <> ''").groupBy("doc_id", "text_key").agg(F.min("spans").alias("spans")).select(F.col("doc_id").alias("d"), F.col("text_key").alias("k"), "spans")
    docs, back = apart(docs, ("doc_id", "text", "n_chars"))
    keyed = docs.withColumn("_key", F.xxhash64(F.coalesce("text", F.lit(""))))
    both = keyed.join(found_, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("_key") == F.col("k")), "left")

    def run():
        def work(texts, spans):
            out = []
            for t, said in zip(texts, spans, strict=True):
                if said:
                    parts, at = [], 0
                    for kind, s, e in (x.split(":") for x in said.split(",")):
                        s, e = int(s), int(e)
                        if s >= at:
                            parts += [t[at:s], f"<{kind.upper()}>"]
                        at = max(at, e)
                    t = "".join([*parts, t[at:]])
                out.append(t)
            return [out]

        return work

    names = docs.columns
    others = [c for c in names if c != "text"]
    new = map_batches(both, others, ["text", "spans"], [T.StructField("text", T.StringType())], run)
    return back(new.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in names else new)
