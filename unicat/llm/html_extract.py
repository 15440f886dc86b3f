"""Main text of web pages by a tree-structured graphical model over DOM nodes.

Each element is a node with a hidden state, content or not. Its unary potential comes from a logistic model of its own
features; its bond with its parent is one of the PARENTS potentials, by what the child is. Sum-product messages pass
from the leaves up and back down, which gives each node's exact content marginal. Text belongs to the nearest
block-level element and is kept if that element's marginal is over one half.

The potentials are fitted on labelled pages: the generator in training_pages() writes pages of many layouts with a known
label on every node, TRAINING_PAGES of them, a fixed and documented bound. Unary and bond weights together have the greatest likelihood of
those labels, with gradients from the same message passing.

Defined cases: a null or empty page has an empty text. Unclosed, misnested and stray tags are closed as browsers do in
the common cases. Pages of any length and depth are read whole, without recursion. Repeated rows are judged alone; extra
columns pass through; an empty table gives an empty table.
"""

from __future__ import annotations

import functools
import html
import math
import random
import re
from collections import defaultdict
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import aside, back, named

TRAINING_PAGES = 240
#: A tag whose attributes are short; longer ones are read by _tag_end(). Nothing in it goes back, so its time is bounded.
_TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)((?:[^>\"']{1,400}+|\"[^\"]{0,400}+\"|'[^']{0,400}+'){0,12}+)>")
_NAME = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)")
_STOP = re.compile(r"[>\"']")
#: Tags of a page that may turn out to end inside a quotation; from then on quotation marks in tags count as any character.
MOST_BAD_TAGS = 20
_ATTR = re.compile(r"(class|id|role|hidden|style|aria-hidden|itemprop)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?", re.I)
_SPACE = re.compile(r"\s+")
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea iframe svg math object canvas title xmp noembed noframes".split())
_RAW_END = {tag: re.compile(rf"</{tag}\b[^>]*>", re.I) for tag in RAW}
INLINE = frozenset("a abbr b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q ruby rb rp rt s samp small span strike strong sub sup time tt u var wbr acronym".split())
#: Opening one of these ends an open paragraph.
_ENDS_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split())
_ENDS = {"li": ("li", {"ul", "ol", "menu"}), "dt": ("dt dd", {"dl"}), "dd": ("dt dd", {"dl"}), "tr": ("tr td th", {"table"}), "td": ("td th", {"tr", "table"}), "th": ("td th", {"tr", "table"}), "option": ("option", {"select"})}
_SAYS_NOT = re.compile(r"(?:^|[-_ ])(?:nav(?:bar|igation)?|menu|header|masthead|footer|foot|side(?:bar)?|aside|widget|ads?|advert\w*|adsense|banner|sponsor\w*|promo\w*|cookies?|consent|notice|alert|popup|modal|overlay|newsletter|subscri\w*|sign-?up|login|social|share|sharing|related|recommend\w*|more-stories|breadcrumbs?|pagination|pager|comments?|respond|discussion|disqus|reply|replies|copyright|legal|disclaimer|toolbar|search|tags?|skip|gdpr|paywall|outbrain|taboola)(?:$|[-_ 0-9])", re.I)
_SAYS_YES = re.compile(r"(?:^|[-_ ])(?:article|main|content|post|entry|story|body(?:text)?|text|prose|articlebody|article-body|post-body)(?:$|[-_ 0-9])", re.I)
_NOT_TAGS = frozenset("nav header footer aside form menu dialog button select fieldset address script style noscript template textarea iframe svg math object canvas head title input".split())
_BLOCK_YES = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre figcaption dd dt li td th".split())


@dataclass
class Node:
    tag: str
    attrs: str
    parent: int
    text: int = 0  # characters of text under it that are not inside links
    linked: int = 0
    own: int = 0
    commas: int = 0


def _tag_end(page: str, at: int, last: dict[str, int]) -> int:
    """The place of the > that ends a tag whose attributes start at a place, or -1. last: where each quotation mark occurs last."""
    while (m := _STOP.search(page, at)) is not None:
        i, mark = m.start(), m[0]
        if mark == ">":
            return i
        at = i + 1 if i >= last[mark] else page.find(mark, i + 1) + 1  # a mark without a second one is any character
    return -1


def _tokens(page: str):
    """(kind, name, text) in page order: text, tags ("<" and "</", with their attributes). Linear in the page: each place
    is looked at a bounded number of times, whatever is left open. What raw elements hold is skipped."""
    at, n, bad = 0, len(page), 0
    last_end, last = page.rfind(">"), {c: page.rfind(c) for c in "\"'"}
    while at < n:
        lt = page.find("<", at)
        if lt < 0 or lt > last_end and not page.startswith("<!--", lt):
            yield "text", "", page[at:]
            return
        if lt > at:
            yield "text", "", page[at:lt]
        if page.startswith("<!--", lt):
            end = page.find("-->", lt + 4)
            at = n if end < 0 else end + 3
            continue
        m = _TAG.match(page, lt)
        if m is not None:
            at, tag = m.end(), m[2].lower()
            yield "</" if m[1] else "<", tag, m[3]
            if tag in RAW and not m[1]:
                end = _RAW_END[tag].search(page, at)
                at = n if end is None else end.end()
            continue
        m = _NAME.match(page, lt)
        if m is None:
            if page[lt + 1 : lt + 2] in ("!", "?"):
                at = page.find(">", lt) + 1
            else:
                yield "text", "", "<"
                at = lt + 1
            continue
        end = _tag_end(page, m.end(), last) if bad < MOST_BAD_TAGS else -1
        if end < 0:
            bad, end = bad + 1, page.find(">", m.end())
        at, tag = end + 1, m[2].lower()
        yield "</" if m[1] else "<", tag, page[m.end() : end]
        if tag in RAW and not m[1]:
            end = _RAW_END[tag].search(page, at)
            at = n if end is None else end.end()


def parse(page: str) -> tuple[list[Node], list[tuple[int, str]]]:
    """(nodes in page order, pieces): a piece is (block node, decoded text), or (block node, "\0") where a block begins or ends.

    Each step looks at the tops of a few stacks only, so the time is linear however many elements are left open."""
    nodes, pieces = [Node("#root", "", -1)], []
    stack: list[tuple[int, str, bool]] = [(0, "#root", True)]  # node, tag, whether it is a block
    block, links = [0], 0
    solid, parents = [0], [0]  # depths of elements that are not inline, and of those that can be parents
    depths: dict[str, list[int]] = defaultdict(list)  # depths at which a tag is open

    def close_to(depth: int) -> None:
        nonlocal links
        while len(stack) > depth:
            _, tag, is_block = stack.pop()
            depths[tag].pop()
            while solid[-1] >= len(stack):
                solid.pop()
            while parents[-1] >= len(stack):
                parents.pop()
            if tag == "a":
                links -= 1
            if is_block:
                block.pop()
                pieces.append((block[-1], "\0"))

    def deepest(tags) -> int:
        return max((depths[t][-1] for t in tags if depths[t]), default=0)

    def add(raw: str) -> None:
        text = html.unescape(raw) if "&" in raw else raw
        size = len(text.strip())
        pieces.append((block[-1], text))
        if size:
            node = nodes[block[-1]]
            node.own += size
            node.commas += text.count(",") + text.count(".")
            if links:
                node.linked += size
            else:
                node.text += size

    for kind, tag, rest in _tokens(page):
        if kind == "text":
            add(rest)
            continue
        if kind == "</":
            limit = depths[tag][-1] if depths[tag] else 0
            # A stray inline end tag does not close blocks that opened after it.
            if limit and not (tag in INLINE and solid[-1] >= limit):
                close_to(limit)
            continue
        if tag in VOID:
            if tag == "br":
                pieces.append((block[-1], " "))
            elif tag not in INLINE:
                pieces.append((block[-1], "\0"))
            continue
        if tag in _ENDS_P and solid[-1] and stack[solid[-1]][1] == "p":
            close_to(solid[-1])
        if tag in _ENDS:
            ends, scope = _ENDS[tag]
            if (end := deepest(ends.split())) > deepest(scope):
                close_to(end)
        attrs = " ".join(f"{a.lower()} {x or y or z or ''}" if a.lower() in ("hidden", "style", "aria-hidden") else f"{x or y or z or ''}" for a, x, y, z in _ATTR.findall(rest)) if "=" in rest or "hidden" in rest else ""
        nodes.append(Node(tag, attrs, stack[parents[-1]][0]))
        own, inline = len(nodes) - 1, tag in INLINE
        if tag in RAW:
            continue
        if rest.endswith("/") and tag in ("svg", "math"):
            continue
        says_not = inline and bool(attrs) and bool(_SAYS_NOT.search(attrs))
        if tag == "a":
            links += 1
        if not inline:
            pieces.append((block[-1], "\0"))
            block.append(own)
            pieces.append((own, "\0"))
            solid.append(len(stack))
        elif says_not:
            # An inline element that says what it is counts as a block of its own for its text.
            block.append(own)
            nodes[own].tag = f"{tag}*"
        if not inline or says_not:
            parents.append(len(stack))
        depths[tag].append(len(stack))
        stack.append((own, tag, not inline or says_not))
    return nodes, pieces


FEATURES = ("bias", "not_tag", "says_not", "says_yes", "article_tag", "block_tag", "own_text", "own_log", "link_share", "commas", "heading", "list_item", "bare_container")
_BARE = frozenset(("div", "body", "section", "#root", "html"))
#: Bonds between parent and child, by the child: marked as no content, a container, a block of text, marked as content.
PARENTS = 4


@functools.lru_cache(4096)
def _marks(attrs: str) -> tuple[bool, bool, bool]:
    """What the attributes say: not content, content, hidden."""
    says_not = bool(_SAYS_NOT.search(attrs))
    hidden = "display:none" in attrs.replace(" ", "") or attrs.startswith("hidden") or "aria-hidden true" in attrs
    return says_not, not says_not and bool(_SAYS_YES.search(attrs)), hidden


def features(nodes: list[Node]) -> tuple[np.ndarray, list[int]]:
    """(nodes by FEATURES, kind of bond with the parent)."""
    rows, bond = [], []
    for v in nodes:
        tag = v.tag.rstrip("*")
        says_not, says_yes, hidden = _marks(v.attrs) if v.attrs else (False, False, False)
        whole = v.text + v.linked
        article, block, no = tag in ("article", "main"), tag in _BLOCK_YES, tag in _NOT_TAGS or hidden
        rows.append((1, no, says_not, says_yes, article, block, v.own > 0, math.log1p(v.own) / 5, v.linked / whole if whole else 0, min(v.commas, 10) / 10, tag in ("h1", "h2", "h3"), tag == "li", tag in _BARE and not says_yes))
        bond.append(0 if no or says_not else 3 if article or says_yes else 2 if block or tag in INLINE else 1)
    return np.array(rows, float), bond


def marginals(parents: list[int], unary: list[float], bond: list[int], pair) -> list[float]:
    """P(content) of every node by sum-product over log-odds. parents[i] < i; pair: log potentials [bond][parent][child]."""
    exp, log = math.exp, math.log
    n = len(parents)
    belief = [min(60.0, max(-60.0, u)) for u in unary]
    up = [0.0] * n
    for i in range(n - 1, 0, -1):  # from the leaves up: children come after their parents
        (p00, p01), (p10, p11) = pair[bond[i]]
        odds = exp(min(60.0, max(-60.0, belief[i])))
        up[i] = log((exp(p10) + exp(p11) * odds) / (exp(p00) + exp(p01) * odds))
        belief[parents[i]] += up[i]
    for i in range(1, n):  # and back down, without what the child itself has sent
        (p00, p01), (p10, p11) = pair[bond[i]]
        odds = exp(min(60.0, max(-60.0, belief[parents[i]] - up[i])))
        belief[i] += log((exp(p01) + exp(p11) * odds) / (exp(p00) + exp(p10) * odds))
    return [1 / (1 + exp(-min(500.0, max(-500.0, v)))) for v in belief]


def training_pages(count: int = TRAINING_PAGES, seed: int = 11):
    """(page, labels of its nodes in page order): labels are written by the generator into a data-k attribute."""
    r = random.Random(seed)

    def words(n):
        return " ".join("".join(r.choice("aeioulmnrst") for _ in range(r.randint(2, 8))) for _ in range(n))

    def sentence(n):
        return words(n).capitalize() + r.choice([".", ".", ", " + words(5) + ".", "!"])

    def paragraph():
        return "".join(f"{sentence(r.randint(2, 18))} " for _ in range(r.choice([1, 1, 2, 4, 8])))

    def links(n, k="0"):
        return f"<ul data-k={k}>" + "".join(f'<li data-k={k}><a data-k={k} href="#">{words(r.randint(1, 3))}</a></li>' for _ in range(n)) + "</ul>"

    def junk():
        kind = r.choice(["nav", "header", "footer", "aside", "ad", "comments", "form", "cookie", "related", "share", "plain-foot"])
        name = r.choice([kind, f"{kind}-box", f"site-{kind}", f"{kind} wide"])
        attr = r.choice(["class", "id"])
        if kind in ("nav", "header", "footer", "aside"):
            inner = r.choice([links(r.randint(2, 7)), f"<p data-k=0>{paragraph()}</p>", sentence(6)])
            return r.choice([f"<{kind} data-k=0>{inner}</{kind}>", f'<div data-k=0 {attr}="{name}">{inner}</div>'])
        if kind == "form":
            return f"<form data-k=0><label data-k=0>{words(2)}</label><button data-k=0>{words(1)}</button><p data-k=0>{sentence(8)}</p></form>"
        if kind == "comments":
            return f'<section data-k=0 {attr}="{name}"><h3 data-k=0>{words(2)}</h3>' + "".join(f'<div data-k=0 class="comment"><p data-k=0>{paragraph()}</p></div>' for _ in range(r.randint(1, 4))) + "</section>"
        if kind == "plain-foot":
            return f"<footer data-k=0>&copy; {words(1)} &middot; {sentence(9)}</footer>"
        body = r.choice([f"<p data-k=0>{paragraph()}</p>", sentence(r.randint(3, 20)), links(3)])
        return f'<div data-k=0 {attr}="{name}">{body}</div>'

    def article():
        out = [f"<h1 data-k=1>{sentence(6)}</h1>"] if r.random() < 0.8 else []
        for _ in range(r.randint(1, 9)):
            out.append(
                r.choice([f"<p data-k=1>{paragraph()}</p>"] * 6 + [f"<p data-k=1><b data-k=1>{sentence(9)}</b><br>{paragraph()}</p>", f"<h2 data-k=1>{words(3)}</h2>", f"<blockquote data-k=1>{paragraph()}</blockquote>", f'<ul data-k=1><li data-k=1>{sentence(5)}</li><li data-k=1>{sentence(7)} <a data-k=1 href="#">{words(2)}</a></li></ul>', f"<p data-k=1>{words(3)}</p>", f"<div data-k=1>{paragraph()}</div>", f"<table data-k=1><tr data-k=1><td data-k=1>{words(2)}</td><td data-k=1>{sentence(4)}</td></tr></table>"])
            )
            if r.random() < 0.15:
                out.append(junk())
        return "".join(out)

    for _ in range(count):
        inner = article()
        style = r.random()
        if style < 0.45:
            main = f"<article data-k=1>{inner}</article>"
        elif style < 0.6:
            main = f"<main data-k=1>{inner}</main>"
        elif style < 0.9:
            main = f'<div data-k=1 class="{r.choice(["content", "post", "article-body", "entry", "story"])}">{inner}</div>'
        else:
            main = inner
        outer = "<body data-k=1>" if style >= 0.9 else "<body data-k=0>"
        yield f"<html data-k=0><head data-k=0><title data-k=0>{words(4)}</title><style data-k=0>p{{}}</style><script data-k=0>var t='</p>';</script></head>{outer}" + "".join(junk() for _ in range(r.randint(0, 3))) + main + "".join(junk() for _ in range(r.randint(0, 3))) + "</body></html>"


def _expected(parents: list[int], unary: list[float], bond: list[int], pair, total: np.ndarray) -> list[float]:
    """Node marginals; adds the pair marginals to total [bond, parent, child]."""
    p = marginals(parents, unary, bond, pair)
    exp, log = math.exp, math.log
    n = len(parents)
    low = [min(60.0, max(-60.0, u)) for u in unary]
    up = [0.0] * n
    for i in range(n - 1, 0, -1):
        (p00, p01), (p10, p11) = pair[bond[i]]
        odds = exp(min(60.0, max(-60.0, low[i])))
        up[i] = log((exp(p10) + exp(p11) * odds) / (exp(p00) + exp(p01) * odds))
        low[parents[i]] += up[i]
    for i in range(1, n):
        top = p[parents[i]]
        for state, share in ((0, 1 - top), (1, top)):
            q0, q1 = pair[bond[i]][state]
            one = 1 / (1 + exp(min(500.0, max(-500.0, q0 - q1 - low[i]))))
            total[bond[i], state, 1] += share * one
            total[bond[i], state, 0] += share * (1 - one)
    return p


@functools.cache
def fitted(pages: int = TRAINING_PAGES, steps: int = 80) -> tuple[np.ndarray, list]:
    """(unary weights, log pair potentials) of greatest likelihood, the same in every process: observed less expected counts,
    with the expectations from exact sum-product, by Adam's steps."""
    label = re.compile(r" data-k=([01])")
    data, seen = [], np.zeros((PARENTS, 2, 2))
    for page in training_pages(pages):
        nodes, _ = parse(label.sub("", page))
        y = [0, *(int(k) for k in label.findall(page))]
        assert len(y) == len(nodes)
        x, bond = features(nodes)
        parents = [v.parent for v in nodes]
        for i in range(1, len(y)):
            seen[bond[i], y[parents[i]], y[i]] += 1
        data.append((x, bond, parents))
    ys = [np.array([0, *(int(k) for k in label.findall(page))]) for page in training_pages(pages)]
    observed = sum(y @ x for y, (x, _, _) in zip(ys, data, strict=True))
    size, scale = len(FEATURES), float(sum(map(len, ys)))
    w = np.zeros(size + seen.size)
    first, second = np.zeros_like(w), np.zeros_like(w)
    for step in range(1, steps + 1):
        total, expected, pair = np.zeros_like(seen), np.zeros(size), w[size:].reshape(seen.shape).tolist()
        for x, bond, parents in data:
            expected += np.array(_expected(parents, (x @ w[:size]).tolist(), bond, pair, total)) @ x
        g = np.concatenate([observed - expected, (seen - total).ravel()]) / scale - 1e-4 * w
        first, second = 0.9 * first + 0.1 * g, 0.99 * second + 0.01 * g * g
        w = w + 0.25 * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.99**step)) + 1e-8)
    return w[:size], w[size:].reshape(seen.shape).tolist()


def extract(page: str | None, model=None) -> str:
    """The main text: blocks in page order, joined by blank lines."""
    if not page:
        return ""
    w, pair = model or fitted()
    nodes, pieces = parse(page)
    x, bond = features(nodes)
    keep = [p > 0.5 for p in marginals([v.parent for v in nodes], (x @ w).tolist(), bond, pair)]
    out, part = [], []
    for node, text in pieces:
        if text == "\0":
            if part:
                out.append("".join(part))
                part = []
        elif keep[node]:
            part.append(text)
    out.append("".join(part))
    return "\n\n".join(b for b in (_SPACE.sub(" ", x).strip() for x in out) if b)


def extract_text(df: DataFrame, html_col: str = "html", drop_html: bool = True) -> DataFrame:
    """df with __text, the page's main text, and __n_chars."""
    df, names_in = aside(df)
    html_col = named(html_col, names_in)
    names = [c for c in df.columns if not (drop_html and c == html_col)]
    schema = T.StructType([*(df.schema[c] for c in names), T.StructField("__text", T.StringType()), T.StructField("__n_chars", T.LongType())])
    held = df.sparkSession.sparkContext.broadcast(fitted())

    def run(batches):
        for b in batches:
            texts = [extract(x.as_py(), held.value) for x in b.column(b.schema.get_field_index(html_col))]
            yield pa.RecordBatch.from_arrays([*(b.column(b.schema.get_field_index(c)) for c in names), pa.array(texts, pa.string()), pa.array([len(x) for x in texts], pa.int64())], schema.names)

    return back(df.mapInArrow(run, schema), names_in)
