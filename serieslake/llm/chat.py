"""Chat formatting by incremental black-box rendering.

A template is any function from a list of (role, text) turns to one string. Successive prefixes
of the turns are rendered; what a render adds to the one before is the span of its last turn. A
render that doesn't begin with the one before shows a template that rewrites history: its spans
are then found from the common prefix and the conversation is flagged. Where a turn's text
stands inside its span is found by rendering two probes instead of the text, so nothing about
the template is assumed.

Every prefix is rendered, so any rewriting of what was shown before is seen, at a cost of the square of
a conversation's turns; the default template keeps the strings of its turns.

Null texts and roles are empty. Equal turn numbers are ordered by role, then text; repeated rows
are repeated turns. Rows of a null conv_id form one conversation. An empty table gives no rows;
other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Callable
from functools import lru_cache

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import map_batches, sha

Template = Callable[[list[tuple[str, str]]], str]
PROBES = ("1", "2")
MARK, END = "### ", " </turn>\n"


def escape(text: str) -> str:
    return re.sub(r"([\\#<:])", r"\\\1", text)


def unescape(text: str) -> str:
    return re.sub(r"\\(.)", r"\1", text, flags=re.S)


def marked_turns(turns: list[tuple[str, str]]) -> str:
    """The default template: ``### role: text </turn>`` lines with control characters escaped."""
    return "".join([_line(*turn) for turn in turns])


@lru_cache(maxsize=1 << 14)
def _line(role: str, text: str) -> str:
    return f"{MARK}{escape(role)}: {escape(text)}{END}"


def read_turns(formatted: str) -> list[tuple[str, str]]:
    """The turns of a string that :func:`marked_turns` made."""
    return [(unescape(m[1]), unescape(m[2])) for m in re.finditer(r"### ((?:[^\\:]|\\.)*): ((?:[^\\<]|\\.)*) </turn>\n", formatted, flags=re.S)]


def _common(a: str, b: str) -> int:
    """How many leading signs two strings share, by halving."""
    lo, hi = 0, min(len(a), len(b))
    while lo < hi:
        mid = (lo + hi + 1) // 2
        if a[lo:mid] == b[lo:mid]:
            lo = mid
        else:
            hi = mid - 1
    return lo


def _text_span(template: Template, before: list, role: str, shown: str, shared: int) -> tuple[int, int]:
    """Where the last turn's text stands in ``shown``, the render of all turns, whose first ``shared`` signs the
    render of the turns before has too."""
    one, two = (template([*before, (role, p)]) for p in PROBES)
    known = shared if one[:shared] == two[:shared] == shown[:shared] else 0
    one, two = one[known:], two[known:]
    head = _common(one, two)
    tail = _common(one[::-1], two[::-1])
    extra = len(shown) - known - len(one)
    return known + head, known + max(head, len(one) - tail + extra)


class Rendered:
    """The formatted text with (start, end) of each turn and of its text, and whether history was rewritten."""

    def __init__(self, turns: list[tuple[str, str]], template: Template):
        self.turns, self.texts, self.rewritten, before = [], [], False, template([])
        self.text = before if turns else ""
        for k in range(len(turns)):
            now = template(turns[: k + 1])
            shared = len(before) if now.startswith(before) else _common(before, now)
            self.rewritten |= shared < len(before)
            self.turns.append((shared, len(now)))
            self.texts.append(_text_span(template, turns[:k], turns[k][0], now, shared))
            self.text = before = now


def render(conversations: DataFrame, template: Template = marked_turns) -> DataFrame:
    """conv_id, formatted, turn_spans and loss_spans (flat start, end lists; loss: the assistant's texts), rewritten."""
    turns = conversations.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")))).alias("turns"))

    def run():
        def work(all_turns):
            out = [[], [], [], []]
            for rows in all_turns:
                pairs = [(r["role"], r["text"]) for r in rows]
                got = Rendered(pairs, template)
                loss = [x for (role, _), span in zip(pairs, got.texts, strict=True) if role == "assistant" for x in span]
                for col, v in zip(out, (got.text, [x for s in got.turns for x in s], loss, got.rewritten), strict=True):
                    col.append(v)
            return out

        return work

    spans = T.ArrayType(T.LongType())
    return map_batches(turns, ["conv_id"], ["turns"], [T.StructField("formatted", T.StringType()), T.StructField("turn_spans", spans), T.StructField("loss_spans", spans), T.StructField("rewritten", T.BooleanType())], run)


def digests(rendered: DataFrame) -> DataFrame:
    """What can be read back from the output: turns, loss text and their digests."""

    def run():
        def work(texts, losses):
            out = [[] for _ in range(5)]
            for text, loss in zip(texts, losses, strict=True):
                turns = read_turns(text)
                said = unescape("".join(text[a:b] for a, b in zip(loss[::2], loss[1::2], strict=True)))
                for col, v in zip(out, (len(turns), sha("".join(f"{r}\n{t}\n" for r, t in turns)), len(said), sha(said), len(text)), strict=True):
                    col.append(v)
            return out

        return work

    long, string = T.LongType(), T.StringType()
    fields = [T.StructField(n, k) for n, k in (("n_turns", long), ("turns_sha256", string), ("loss_chars", long), ("loss_sha256", string), ("formatted_chars", long))]
    return map_batches(rendered, ["conv_id"], ["formatted", "loss_spans"], fields, run)
