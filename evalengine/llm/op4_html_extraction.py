"""Main-text extraction with a tree-structured graphical model over the DOM.

Each block element is a binary variable, content or not. Unary potentials weigh the tag, the words of its
class, id and role, and the amount, punctuation and link share of its text; a 2x2 table ties each node to
its parent. Sum-product messages go up the tree and down again, which gives every node's exact marginal.
``train`` fits all potentials by gradient ascent on the likelihood of labelled pages (``labelled_pages``
writes such pages in many layouts, with the truth known); its gradient is observed minus expected counts.

Extraction is one narrow Arrow step: pages are independent and nothing is shuffled.

Defined cases: null or empty html gives an empty text; a text without tags is one block; unclosed tags, comments
and scripts end where browsers end them; character references are decoded once; white space, no-break
spaces included, becomes one space; a page of any length is read whole; repeated rows each give a row; an empty table
gives an empty result; a marginal of exactly one half is no content; extra columns are ignored.
"""

from __future__ import annotations

import html as entities
import math
import random
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evalengine.llm._common import table

# Element names by how a parser treats them.
BLOCKS = frozenset("html body header nav main article section aside footer div ul ol li dl dt dd p h1 h2 h3 h4 h5 h6 table thead tbody tfoot tr td th caption form fieldset blockquote pre figure figcaption details summary address hgroup center dialog menu".split())
SILENT = frozenset("head title script style noscript template iframe svg math object select button textarea option datalist canvas audio video map".split())
LANDMARKS = frozenset("article main nav aside header footer form section table".split())
RAW = frozenset("script style textarea title iframe noscript".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
CLOSED_BY = {"li": frozenset(["li"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"]), "tr": frozenset(["tr", "td", "th"]), "td": frozenset(["td", "th"]), "th": frozenset(["td", "th"]), "option": frozenset(["option"])}
SCOPES = frozenset("html body table td th div section article aside nav main header footer ul ol dl form blockquote figure".split())
# Words in class, id and role, by what they tell.
HINTS = {
    "content": "content article post entry story body text main prose",
    "menu": "nav navbar navigation menu breadcrumb breadcrumbs pagination pager toc tabs skip",
    "head": "header masthead topbar banner branding logo",
    "foot": "footer copyright legal colophon contentinfo bottom",
    "side": "sidebar side aside rail complementary widget related recommended recommendations popular trending more",
    "advert": "ad ads advert advertisement advertising adsense sponsor sponsored promo promotion dfp",
    "notice": "cookie cookies consent gdpr notice alert popup modal overlay newsletter subscribe signup paywall",
    "comments": "comment comments disqus reply replies discussion respond reactions",
    "form": "form search login register input",
    "share": "share sharing social follow tags meta byline author",
}
HINT_OF = {w: k for k, v in HINTS.items() for w in v.split()}

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:\"[^\"]*\"|'[^']*'|[^'\">])*)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>", re.S)
_NAMES = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_WORDS = re.compile(r"[a-z]+")


@dataclass
class Node:
    tag: str
    parent: int
    hints: frozenset[str]
    silent: bool
    texts: list[int] = field(default_factory=list)
    own: int = 0
    linked: int = 0
    stops: int = 0


def parse(page: str) -> tuple[list[Node], list[tuple[int, str]]]:
    """Block nodes in document order (node 0 is the document), and the blocks of text as (node, raw text)."""
    nodes = [Node("#document", -1, frozenset(), False)]
    stack: list[tuple[str, int]] = [("#document", 0)]
    blocks: list[tuple[int, str]] = []
    held: list[str] = []
    links, at, pos = 0, 0, 0

    def close() -> None:
        nonlocal held
        if held:
            text = "".join(held)
            if not text.isspace():
                nodes[at].texts.append(len(blocks))
                blocks.append((at, text))
            held = []

    def say(text: str) -> None:
        if text and not nodes[at].silent:
            held.append(text)
            n = len(text)
            nodes[at].own += n
            nodes[at].stops += text.count(".") + text.count(",")
            if links:
                nodes[at].linked += n

    def pop(k: int) -> None:
        nonlocal at, links
        for name, _ in stack[k:]:
            links -= name == "a"
        del stack[k:]
        at = stack[-1][1]

    while True:
        m = _TAG.search(page, pos)
        if m is None:
            say(page[pos:])
            break
        if m.start() > pos:
            say(page[pos : m.start()])
        pos = m.end()
        name = m[2] or m[5]
        if name is None:
            continue
        name, ending, attrs = name.lower(), bool(m[1] or m[4]), m[3] or m[6] or ""
        if name in VOID:
            if name in ("br", "hr"):
                say(" ")
            if name == "hr":
                close()
            continue
        block = name in BLOCKS or name in SILENT
        if ending:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] == name:
                    if block or any(x in BLOCKS for x, _ in stack[k:]):
                        close()
                    pop(k)
                    break
                if not block and stack[k][0] in BLOCKS:
                    break
            continue
        if block:
            close()
            ends = CLOSED_BY.get(name, ())
            for k in range(len(stack) - 1, 0, -1):
                top = stack[k][0]
                if top == "p" and name not in SILENT or top in ends:
                    pop(k)
                    break
                if top in SCOPES:
                    break
            hints = frozenset(HINT_OF[w] for x in _NAMES.findall(attrs) for w in _WORDS.findall("".join(x).lower()) if w in HINT_OF) if attrs else frozenset()
            nodes.append(Node(name, at, hints, nodes[at].silent or name in SILENT))
            at = len(nodes) - 1
        if attrs.endswith("/") and not block:
            continue
        stack.append((name, at))
        links += name == "a"
        if name in RAW:
            end = re.compile(rf"</{name}\b", re.I).search(page, pos)
            pos = end.start() if end else len(page)
    close()
    return nodes, blocks


def features(nodes: list[Node]) -> list[list[str]]:
    """Names of the features that are on at each node."""
    own, linked, stops = [n.own for n in nodes], [n.linked for n in nodes], [n.stops for n in nodes]
    for i in range(len(nodes) - 1, 0, -1):
        p = nodes[i].parent
        own[p] += own[i]
        linked[p] += linked[i]
        stops[p] += stops[i]
    out, inside = [], []
    for i, n in enumerate(nodes):
        above = inside[n.parent] if i else frozenset()
        inside.append(above | {n.tag} if n.tag in LANDMARKS else above)
        size = min(3, int(math.log10(1 + n.own) * 1.3))
        share = 0 if not own[i] else min(3, int(4 * linked[i] / own[i]))
        f = ["bias", f"tag {n.tag}", f"size {size}", f"links {share}", f"size {size} links {share}"]
        if not above:
            f.append(f"stops {min(3, stops[i])}")
        f += [f"hint {h}" for h in n.hints] or ["no hint"]
        f += [f"inside {t}" for t in above] or ["in no landmark"]
        if n.own > 30:
            f.append("speaks")
        if n.silent:
            f.append("silent")
        out.append(f)
    return out


def marginals(unary: list[float], parent: list[int], tie: tuple[float, float, float, float]) -> tuple[list[float], list[float]]:
    """Exact P(content) of every node, and the expected number of edges by (parent, child) label 00, 01, 10, 11.

    ``unary`` is the log potential of content against none; node 0 is the root, parents come before children.
    """
    n = len(unary)
    e00, e01, e10, e11 = (math.exp(t) for t in tie)
    up0, up1 = [1.0] * n, [math.exp(max(-30.0, min(30.0, u))) for u in unary]
    to0, to1 = [1.0] * n, [1.0] * n
    for i in range(n - 1, 0, -1):
        z = up0[i] + up1[i]
        a, b = up0[i] / z, up1[i] / z
        up0[i], up1[i] = a, b
        m0, m1 = e00 * a + e01 * b, e10 * a + e11 * b
        z = m0 + m1
        to0[i], to1[i] = m0 / z, m1 / z
        p = parent[i]
        up0[p] *= to0[i]
        up1[p] *= to1[i]
        if (z := up0[p] + up1[p]) < 1e-100 or z > 1e100:
            up0[p] /= z
            up1[p] /= z
    belief = [0.0] * n
    z = up0[0] + up1[0]
    belief[0] = up1[0] / z
    counts = [0.0] * 4
    for i in range(1, n):
        b1 = belief[parent[i]]
        c0, c1 = (1 - b1) / to0[i], b1 / to1[i]
        j = (c0 * e00 * up0[i], c0 * e01 * up1[i], c1 * e10 * up0[i], c1 * e11 * up1[i])
        z = sum(j)
        belief[i] = (j[1] + j[3]) / z
        for k in range(4):
            counts[k] += j[k] / z
    return belief, counts


@dataclass
class Model:
    weights: dict[str, float]
    tie: tuple[float, float, float, float]

    def beliefs(self, nodes: list[Node]) -> list[float]:
        get = self.weights.get
        return marginals([sum([get(f, 0.0) for f in fs]) for fs in features(nodes)], [n.parent for n in nodes], self.tie)[0]


def train(pages: list[tuple[str, str]], rounds: int = 60, rate: float = 0.5, ridge: float = 0.005) -> Model:
    """Fit on (html, attribute) pages: elements under one that carries ``data-truth="1"`` or ``"0"`` have that label."""
    read = []
    for page in pages:
        nodes, truth = _labelled(*page)
        read.append((features(nodes), [n.parent for n in nodes], truth))
    w: dict[str, float] = {}
    tie, seen, seen_tie = [0.0] * 4, {}, [1e-8] * 4
    for _ in range(rounds):
        grad: dict[str, float] = {}
        grad_tie = [0.0] * 4
        for fs, parent, truth in read:
            belief, counts = marginals([sum([w.get(f, 0.0) for f in x]) for x in fs], parent, tuple(tie))
            for x, b, y in zip(fs, belief, truth, strict=True):
                for f in x:
                    grad[f] = grad.get(f, 0.0) + y - b
            for k in range(4):
                grad_tie[k] -= counts[k]
            for i in range(1, len(parent)):
                grad_tie[2 * truth[parent[i]] + truth[i]] += 1
        for f, g in grad.items():
            g = g / len(read) - ridge * w.get(f, 0.0)
            seen[f] = seen.get(f, 1e-8) + g * g
            w[f] = w.get(f, 0.0) + rate * g / math.sqrt(seen[f])
        for k in range(4):
            g = grad_tie[k] / len(read) - ridge * tie[k]
            seen_tie[k] += g * g
            tie[k] += rate * g / math.sqrt(seen_tie[k])
    return Model(w, tuple(tie))


def _labelled(page: str, mark: str) -> tuple[list[Node], list[int]]:
    """Nodes and labels: in a training page, text of the article holds ``mark``."""
    nodes, blocks = parse(page)
    good, bad = [0] * len(nodes), [0] * len(nodes)
    for i, text in blocks:
        if mark in text:
            good[i] += len(text)
        else:
            bad[i] += len(text)
    for i in range(len(nodes) - 1, 0, -1):
        good[nodes[i].parent] += good[i]
        bad[nodes[i].parent] += bad[i]
    whole = [n.tag in ("article", "main") or "content" in n.hints and n.tag != "body" for n in nodes]
    return nodes, [int(g > b or w and g > 0) for g, b, w in zip(good, bad, whole, strict=True)]


def labelled_pages(n: int = 150, seed: int = 11) -> list[tuple[str, str]]:
    """Training pages in varied layouts; every block of an article holds the mark, no other text does."""
    r = random.Random(seed)
    mark = "⁣"
    parts = "ka lo mi ter ven sol ar ine pro tu des un el ra gim fo".split()
    word = lambda: "".join(r.choice(parts) for _ in range(r.randint(1, 4)))

    def prose(k: int) -> str:
        """Sentences, or now and then words without stops, in capitals, or with symbols."""
        kind = r.random()
        marks = ["", "", "", "", ",", "."] if kind < 0.7 else [""] if kind < 0.8 else ["!!"] if kind < 0.9 else ["%%%", "***", " |"]
        text = " ".join(word() + r.choice(marks) for _ in range(k)) + "." * (kind < 0.7)
        return text.upper() if 0.8 < kind < 0.85 else text

    def links(k: int) -> str:
        return "".join(f'<li><a href="/{word()}">{word()}</a></li>' for _ in range(k))

    def box(tags: list[str], names: list[str], inside: str) -> str:
        tag, name = r.choice(tags), r.choice(names)
        how = r.choice(["class", "id"])
        return f'<{tag} {how}="{name}">{inside}</{tag}>' if name and r.random() < 0.8 or tag == "div" else f"<{tag}>{inside}</{tag}>"

    pages = []
    for _ in range(n):
        own = lambda k: mark + prose(k)
        body = [f"<h1>{own(6)}</h1>"] * r.randint(0, 1)
        for _ in range(r.randint(1, 9)):
            body.append(r.choice([lambda: f"<p>{own(r.choice([2, 9, 40, 90, 300]))}</p>", lambda: f"<p>{own(r.randint(8, 60))}", lambda: f"<p><b>{own(4)}<br><p>{own(30)}</p>", lambda: f"<h2>{own(3)}</h2><p>{own(30)}</p>", lambda: f"<blockquote><p>{own(20)}</p></blockquote>", lambda: "<ul>" + "".join(f"<li>{own(7)}</li>" for _ in range(3)) + "</ul>", lambda: f'<p>{own(20)} <a href="/x">{word()}</a> {prose(9)}</p>', lambda: f"<pre>{own(12)}</pre>", lambda: f"<table><tr><td>{own(2)}</td><td>{own(3)}</td></tr></table>", lambda: f"<p>{own(1)}</p>"])())
        if r.random() < 0.3:
            body.insert(r.randint(0, len(body)), box(["div", "aside"], ["ad", "advert", "promo", "sponsored", "related", "newsletter", "share"], prose(r.randint(3, 12))))
        if r.random() < 0.3:
            said = "".join(box(["div", "li", "article"], ["comment", "reply", "comment-body"], f"<p>{prose(r.randint(3, 40))}</p>") for _ in range(r.randint(1, 4)))
            body.append(box(["section", "div"], ["comments", "comment-list", "discussion", "responses"], (f"<h3>{prose(2)}</h3>" if r.random() < 0.5 else "") + said))
        way = r.random()
        if way < 0.6:
            main = box(["article", "article", "article", "main", "div", "section"], ["content", "post", "entry-content", "article-body", "story", "main"], "".join(body))
        elif way < 0.8:
            main = f"<div>{''.join(body)}</div>" if r.random() < 0.6 else f'<div class="{word()}"><div>{"".join(body)}</div></div>'
        else:
            main = "".join(body)
        before = ["<nav><ul>" + links(r.randint(2, 8)) + "</ul></nav>"] * r.randint(0, 1)
        before += [box(["header", "div"], ["header", "masthead", "banner", ""], f"<h1>{word()} {word()}</h1><p>{prose(5)}</p>")] * (r.random() < 0.5)
        before += [box(["div", "ul"], ["menu", "nav", "navbar", "breadcrumbs"], links(r.randint(2, 6)))] * (r.random() < 0.4)
        before += ["".join(f'<a href="/{word()}">{word()}</a>{r.choice(["", " ", " | "])}' for _ in range(r.randint(2, 5)))] * (r.random() < 0.2)
        before += [box(["div"], ["ad", "ads", "advert-top", "sponsor"], prose(r.randint(2, 14)))] * (r.random() < 0.6)
        before += [box(["div", "section", "p"], ["cookie-notice", "consent", "alert", "gdpr-popup"], prose(r.randint(5, 25)))] * (r.random() < 0.4)
        after = [box(["aside", "div"], ["sidebar", "side", "related", "widget"], r.choice([f"<h3>{word()}</h3><ul>{links(4)}</ul>", f"<p>{prose(20)}</p>", f"<h4>{word()}</h4><p>{prose(9)}</p>"]))] * (r.random() < 0.5)
        after += [box(["section", "div"], ["comments", "comment-list", "disqus", "replies"], "".join(f'<div class="comment"><p>{prose(r.randint(3, 40))}</p></div>' for _ in range(r.randint(1, 4))))] * (r.random() < 0.5)
        after += [f'<form action="/s"><label>{word()}</label><input name="q"><p>{prose(4)}</p><button>{word()}</button></form>'] * (r.random() < 0.4)
        after += [f"<footer><p>{prose(r.randint(3, 12))}</p></footer>" if r.random() < 0.5 else f"<footer>{prose(r.randint(3, 12))}</footer>"] * (r.random() < 0.7)
        after += [box(["div"], ["footer", "copyright", "legal"], prose(r.randint(3, 12)))] * (r.random() < 0.3)
        if r.random() < 0.25:
            before, after = [*before, *after[:1]], after[1:]
        inside = "".join(before) + main + "".join(after)
        if r.random() < 0.12:
            inside = f"<table><tr><td>{''.join(before)}</td><td>{main}</td><td>{''.join(after)}</td></tr></table>"
        if r.random() < 0.4:
            inside = f'<div class="{r.choice(["wrapper", "container", "page", "site"])}">{inside}</div>'
        pages.append((f"<!DOCTYPE html><html><head><title>{word()}</title><style>p{{}}</style></head><body>{inside}</body></html>", mark))
    return pages


def main_text(page: str, model: Model) -> str:
    nodes, blocks = parse(page)
    if not blocks:
        return ""
    belief = model.beliefs(nodes)
    out = []
    for i, text in blocks:
        if belief[i] > 0.5 or len(nodes) == 1:
            text = " ".join((entities.unescape(text) if "&" in text else text).split())
            if text:
                out.append(text)
    return "\n".join(out)


def extract(pages: DataFrame, model: Model) -> DataFrame:
    """``page_id``, ``url``, ``text`` and ``n_chars`` (code points) of every row of ``pages``."""
    shared = pages.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(h or "", shared.value) for h in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")


def op4_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"), train(labelled_pages()))
