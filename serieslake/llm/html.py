"""Main-text extraction by tree scoring.

A page becomes a tree. Paragraphs pass points for length and commas to their ancestors, halved
at each step up and discounted by link density; the container with the most points is the best one.
Inside an ``article`` or ``main`` all of that element is the text. Elsewhere the highest ancestor of the same text and
its worthy siblings are kept: those of many points, and prose of few links however short. Parts that are
no article text by their element, role or class names (menus, footers, notices, adverts, forms, comments and
so on) are cut before the scoring; a paragraph or heading only by the names of adverts and the like.

Time grows with the page's length: each tag is read once, and sums go up and down the tree once.

Null, blank and textless pages give empty text. Markup that never ends is text. Repeated rows give repeated results, an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from html import unescape

from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import map_batches

NAME = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)")
#: The rest of a tag; a quote counts after an equals sign only.
REST = re.compile(r"(?>=\s*\"[^\"]*\"|=\s*'[^']*'|[^>])*+")
ATTRS = re.compile(r"([a-zA-Z-]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
#: Fixed values of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe template svg math xmp noembed noframes".split())
BLOCKS = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul caption br".split())
CLOSES_P = BLOCKS - {"br", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "body", "html"}
IMPLIED = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "tbody": {"thead", "tbody", "tr", "td", "th"}, "tfoot": {"tbody", "tr", "td", "th"}}
SCOPE = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table"}, "th": {"table"}, "tbody": {"table"}, "tfoot": {"table"}, "option": {"select"}}
#: Elements, roles and words of class or id that never hold article text.
CUT_TAGS = frozenset("head nav header footer aside form menu button select dialog fieldset object embed audio video canvas".split()) | RAW
CUT_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar".split())
CUT_WORDS = frozenset("ad ads advert advertisement adverts sponsor sponsored promo nav navbar navigation menu sidebar footer header masthead breadcrumb breadcrumbs comment comments disqus respond cookie cookies consent notice banner popup modal overlay newsletter subscribe signup login share sharing social related recommended widget pagination pager toolbar skip hidden".split())
#: Of these words those that cut paragraphs and headings, too, which otherwise go by their points.
CUT_PROSE = frozenset("ad ads advert advertisement adverts sponsor sponsored promo breadcrumb breadcrumbs cookie cookies consent newsletter pagination pager".split())
PROSE = frozenset("p pre blockquote h1 h2 h3 h4 h5 h6".split())
PARAGRAPHS = frozenset("p pre td blockquote li dd div section article h1 h2 h3 h4 h5 h6".split())
PRIOR = {"article": 25.0, "main": 20.0, "section": 2.0, "div": 2.0, "blockquote": 1.0, "form": -3.0, "ul": -3.0, "ol": -3.0, "li": -3.0, "th": -5.0}


class _Node:
    __slots__ = ("children", "cut", "link", "parent", "tag")

    def __init__(self, tag, parent, cut, link):
        self.tag, self.parent, self.cut, self.link, self.children = tag, parent, cut, link, []


def _is_cut(tag: str, attrs: str) -> bool:
    if tag in CUT_TAGS:
        return True
    if not attrs or tag in ("html", "body"):
        return False
    for m in ATTRS.finditer(attrs):
        name, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
        if name == "hidden" or (name == "aria-hidden" and value == "true") or (name == "role" and value in CUT_ROLES) or (name == "style" and re.search(r"display\s*:\s*none", value)):
            return True
        if name in ("class", "id") and tag not in ("article", "main") and not (CUT_PROSE if tag in PROSE else CUT_WORDS).isdisjoint(re.split(r"[^a-z0-9]+", value)):
            return True
    return False


def _tags(html: str):
    """(begin, end, slash, name, attributes) of tags, and of comments and declarations with an empty name, in order.
    The caller may send the place to go on from."""
    at = 0
    while (at := html.find("<", at)) >= 0:
        if html.startswith(("<!", "<?"), at):
            stop = "-->" if html.startswith("<!--", at) else ">"
            end = html.find(stop, at + (4 if stop == "-->" else 2))
            got = at, len(html) if end < 0 else end + len(stop), "", "", ""
        elif m := NAME.match(html, at):
            if html.find(">", m.end()) < 0:
                return
            end = REST.match(html, m.end()).end()
            if end == len(html):  # a quote that never closes
                end = html.find(">", m.end())
            got = at, end + 1, m[1], m[2].lower(), html[m.end() : end]
        else:
            at += 1
            continue
        at = (yield got) or got[1]


def parse(html: str) -> _Node:
    """The tree of a page, with end tags that HTML lets writers leave out."""
    root = _Node("#root", None, False, False)
    stack, text_from, count = [root], 0, Counter()

    def text(upto):
        if upto > text_from and not stack[-1].cut:
            stack[-1].children.append(html[text_from:upto])

    def drop(k):
        count.subtract(n.tag for n in stack[k:])
        del stack[k:]

    tags, goto = _tags(html), None
    while True:
        try:
            begin, at, slash, tag, attrs = tags.send(goto)
        except StopIteration:
            break
        goto = None
        text(begin)
        text_from = at
        if not tag:
            continue
        if slash:
            for k in range(len(stack) - 1, 0, -1) if count[tag] > 0 else ():
                if stack[k].tag == tag:
                    drop(k)
                    break
                if tag not in BLOCKS and stack[k].tag in BLOCKS:
                    break  # an inline end tag doesn't close a block
            continue
        if tag in CLOSES_P and count["p"] > 0:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == "p":
                    drop(k)
                    break
                if stack[k].tag in BLOCKS:
                    break
        while tag in IMPLIED and any(count[t] > 0 for t in IMPLIED[tag]):
            k = next((k for k in range(len(stack) - 1, 0, -1) if stack[k].tag in IMPLIED[tag] or stack[k].tag in SCOPE[tag]), 0)
            if not k or stack[k].tag in SCOPE[tag]:
                break
            drop(k)
        top = stack[-1]
        node = _Node(tag, top, top.cut or _is_cut(tag, attrs), top.link or tag == "a")
        top.children.append(node)
        if tag in RAW and not attrs.endswith("/"):
            end = re.compile(rf"</{re.escape(tag)}(?=[\s/>])[^>]*>", re.I).search(html, at)
            goto = text_from = end.end() if end else len(html)
        elif tag not in VOID and not attrs.endswith("/"):
            stack.append(node)
            count[tag] += 1
    text(len(html))
    return root


def _blocks(root: _Node):
    """(block element, text, chars in links) in page order; a block ends where another block begins or ends."""
    out, parts, links = [], [], [0]

    def flush(owner):
        if parts:
            said = " ".join(unescape("".join(parts)).split())
            if said:
                out.append((owner, said, min(links[0], len(said))))
            parts.clear()
            links[0] = 0

    work = [(root, root, False)]
    while work:
        item, owner, leave = work.pop()
        if isinstance(item, str):
            parts.append(item)
            if leave:
                links[0] += len(item)
        elif leave is None:
            flush(item)
        elif not item.cut:
            if item.tag in BLOCKS:
                flush(owner)
                if item.tag in VOID:
                    continue
                work.append((item, owner, None))
                owner = item
            work.extend((c, owner, item.link if isinstance(c, str) else False) for c in reversed(item.children))
    flush(root)
    return out


def _preorder(root: _Node) -> list[_Node]:
    out, work = [], [root]
    while work:
        node = work.pop()
        out.append(node)
        work.extend(c for c in reversed(node.children) if not isinstance(c, str))
    return out


def main_text(html: str | None) -> str:
    if not html:
        return ""
    root = parse(html)
    blocks = _blocks(root)
    if not blocks:
        return ""
    nodes = _preorder(root)
    points, passed, chars, linked, prose = ({n: 0.0 for n in nodes} for _ in range(5))
    for owner, said, in_links in blocks:
        worth = (1 + said.count(",") + min(len(said) / 100, 3)) * (1 - in_links / len(said)) if owner.tag in PARAGRAPHS else 0.0
        if len(said) < 25:
            worth /= 10
        if owner.tag in PROSE:
            passed[owner] += worth
            prose[owner] += len(said)
        else:
            points[owner] += worth
            passed[owner] += worth / 2
        chars[owner] += len(said)
        linked[owner] += in_links
    for n in reversed(nodes):  # children come before parents
        if n.parent is not None:
            points[n.parent] += passed[n]
            passed[n.parent] += passed[n] / 2
            for sums in (chars, linked, prose):
                sums[n.parent] += sums[n]
    graded = {n: (PRIOR.get(n.tag, 0.0) + points[n]) * (1 - linked[n] / chars[n]) for n in nodes if chars[n] and n.tag not in PROSE and n is not root}
    best = max(graded, key=graded.get) if graded else root  # the first of equals
    keep, top = set(), best
    while top is not root and top.tag not in ("article", "main"):
        top = top.parent
    if top is root:
        top = best
        while top.parent is not None and chars[top.parent] == chars[top]:
            top = top.parent
        floor = max(10.0, 0.2 * graded.get(best, 0.0))
        for near in top.parent.children if top.parent is not None else ():
            if not isinstance(near, str) and chars[near]:
                density = linked[near] / chars[near]
                if graded.get(near, 0.0) >= floor and density < 0.5 or prose[near] and density < 0.25:
                    keep.add(near)
    keep.add(top)
    inside = set()
    for n in nodes:
        if n in keep or n.parent in inside:
            inside.add(n)
    return "\n".join(said for owner, said, _ in blocks if owner in inside)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every row."""

    def run():
        def work(htmls):
            texts = [main_text(h) for h in htmls]
            return [texts, [len(t) for t in texts]]

        return work

    return map_batches(pages, ["page_id", "url"], ["html"], [T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())], run)
