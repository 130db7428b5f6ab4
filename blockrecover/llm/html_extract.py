"""Main-text extraction by a tree-structured graphical model over the DOM.

Every element and every run of text is a node that is content or not. Node potentials come from features of the
element (its name, words of its class, id and role, link share, text length, punctuation); pairwise potentials tie a
child to its parent, one table per kind of child. Messages go up from the leaves and down from the root (sum-product),
which on a tree gives exact marginals. Weights maximise the likelihood of labelled pages; these are generated by
``labelled_pages``, which writes pages of many layouts together with the label of every element.

A text run whose marginal is at least one half is kept. On a page where none reaches that, the likeliest run, if its marginal
is at least ``LEAST``, is taken as content and the messages pass again: what then reaches one half is kept. Character references are decoded once; white space inside a
block becomes one space; block texts are trimmed, empty ones dropped, and joined in page order by two newlines. A line
break (br) is white space inside its block.

Markup is read in one pass whose cost is linear in the page, whatever is left open in it: a quote that is never closed ends
with its tag, a tag that is never closed ends the page. White space between inline elements separates their texts.

Defined results: null or empty html gives an empty text; broken markup is read leniently (unclosed or stray tags never
fail); elements may nest to any depth; repeated rows each give a row; other columns are ignored.
"""

from __future__ import annotations

import re
from functools import lru_cache
from html import unescape

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template title iframe xmp noembed noframes".split())
#: Elements whose content is text without markup; the model judges it.
PLAIN = frozenset({"textarea"})
BLOCK = frozenset(
    "html body address article aside blockquote center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 header hgroup hr li main menu nav ol p pre search section summary table tbody td tfoot th thead tr ul caption option select button legend".split()
)
CLOSES_P = BLOCK - {"html", "body", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "option", "button", "legend", "summary"}
SAME = {"li": {"li"}, "dd": {"dd", "dt"}, "dt": {"dd", "dt"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "p": {"p"}}
STOPS_AT = frozenset("ul ol dl table tbody thead tfoot body html article section main div nav aside header footer form select".split())
NEXT = re.compile(r"<(?=[a-zA-Z/!?])")
NAME = re.compile(r"(/?)([a-zA-Z][^\s/>]*)")
#: What matters inside a tag: its end, or a quoted value.
INSIDE = re.compile(r">|=\s*([\"'])")
#: A block of the first kind is ended by the start of another of its group, unless one of ``STOPS_AT`` lies between.
TRACKED = frozenset(SAME)
#: An inline end tag does not close these.
BARRIERS = ("td", "th", "table", "body")
ATTRIBUTE = re.compile(r"""\b(class|id|role|itemprop|hidden|style|aria-hidden)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""", re.I)
WORDS = re.compile(r"[a-z]{2,}")
LABEL_WORDS = frozenset(
    "ad ads advert advertisement sponsor sponsored promo banner nav navbar navigation menu header footer sidebar side aside widget related share social comment comments reply disqus cookie consent notice popup modal newsletter subscribe signup form breadcrumb breadcrumbs pagination tags meta copyright legal masthead toolbar search login content article main post entry story body text hidden none contentinfo complementary alert articlebody recommended trending author bio print skip rail feedback discussion thread warning message info gdpr overlay".split()
)


SIDE = frozenset("nav aside footer header form select button figure noscript svg".split())
NAMING = frozenset("article content main post entry story articlebody".split())


class Node:
    __slots__ = ("tag", "parent", "names", "text", "chars", "link_chars", "stops", "block", "scope", "space", "named", "marked")

    def __init__(self, tag, parent, names=(), space=False):
        self.tag, self.parent, self.names = tag, parent, names
        self.text = None
        self.chars = self.link_chars = self.stops = 0
        self.block = self if parent is None or tag in BLOCK else parent.block
        #: the open elements that a start tag may end, with their depths
        self.scope = {} if parent is None or tag in STOPS_AT else parent.scope
        self.space = space  # white space came before
        #: it, or an element around it, says what it is for
        self.marked = bool(names) or tag in SIDE or parent is not None and parent.marked


@lru_cache(maxsize=None)
def closing(tag: str) -> re.Pattern:
    return re.compile(rf"</{re.escape(tag)}\s*>", re.I)


def names_of(attributes: str) -> tuple[str, ...]:
    if not attributes or len(attributes) < 5:
        return ()
    out = []
    for m in ATTRIBUTE.finditer(attributes):
        key, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
        if key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value):
            out.append("hidden")
        elif key not in ("style", "aria-hidden"):
            out += [w for w in WORDS.findall(re.sub(r"([a-z])([A-Z])", r"\1 \2", m[2] or m[3] or m[4] or "").lower()) if w in LABEL_WORDS]
    return tuple(sorted(set(out)))


def tag_end(html: str, at: int) -> tuple[int, int]:
    """(end of the attributes, place behind the tag); a tag that never ends takes the rest."""
    start = at
    while True:
        m = INSIDE.search(html, at)
        if m is None:
            return len(html), len(html)
        if m[1] is None:
            return m.start(), m.end()
        close = html.find(m[1], m.end())
        if close < 0:  # no such quote follows, so this is met once for each kind of quote
            end = html.find(">", start)
            return (end, end + 1) if end >= 0 else (len(html), len(html))
        at = close + 1


def parse(html: str) -> list[Node]:
    """All nodes in document order, the root first; text runs are nodes named ``#``."""
    root = Node("#root", None)
    nodes, path, where = [root], [root], {}  # path: open elements; where: their depths by name
    size, at, space = len(html), 0, False

    def put(text):
        nonlocal space
        if text.isspace():
            space = True
        elif text:
            n = Node("#", path[-1], space=space)
            n.text, space = text, False
            nodes.append(n)

    def close(depth):
        while len(path) > depth:
            where[path.pop().tag].pop()

    while at < size:
        m = NEXT.search(html, at)
        if m is None:
            put(html[at:])
            break
        if m.start() > at:
            put(html[at : m.start()])
        at = m.end()
        if html[at] in "!?":
            opened = next((x for x in ("!--", "![CDATA[") if html.startswith(x, at)), None)
            ending = {"!--": "-->", "![CDATA[": "]]>", None: ">"}[opened]
            end = html.find(ending, at + len(opened or ""))
            at = end + len(ending) if end >= 0 else size
            continue
        m = NAME.match(html, at)
        if m is None:  # a slash that no name follows
            end = html.find(">", at)
            at = end + 1 if end >= 0 else size
            continue
        tag = m[2].lower()
        end, at = tag_end(html, m.end())
        if m[1]:
            depth = where.get(tag) or [0]
            if depth[-1] and (tag in BLOCK or all((where.get(x) or [0])[-1] <= depth[-1] for x in BARRIERS)):
                close(depth[-1])
            continue
        ends = path[-1].scope
        if tag in CLOSES_P and "p" in ends:
            close(ends["p"])
        if tag in SAME:
            near = max((path[-1].scope.get(x, 0) for x in SAME[tag]), default=0)
            if near:
                cell = path[near].tag
                close(near)
                if tag == "tr" and cell in ("td", "th") and path[-1].tag == "tr":
                    close(len(path) - 1)
        attributes = html[m.end() : end]
        n = Node(tag, path[-1], names_of(attributes), space)
        space = False
        nodes.append(n)
        if tag in VOID or attributes.endswith("/"):
            continue
        if tag in RAW or tag in PLAIN:
            m = closing(tag).search(html, at)
            if tag in PLAIN and m is not None and m.start() > at:
                inner = Node("#", n)
                inner.text = html[at : m.start()]
                nodes.append(inner)
            at = m.end() if m else size
            continue
        if tag in TRACKED:
            n.scope = {**n.scope, tag: len(path)}
        where.setdefault(tag, []).append(len(path))
        path.append(n)
    # whether anything on the page says where its article is
    named = any(n.tag in ("article", "main") or not NAMING.isdisjoint(n.names) for n in nodes)
    for n in reversed(nodes):
        n.named = named
        if n.text is not None:
            n.chars = len(n.text)
            n.stops = sum(map(n.text.count, ".,;!?"))
        if n.parent is not None:
            p = n.parent
            p.chars += n.chars
            p.stops += n.stops
            p.link_chars += n.chars if n.tag == "a" else n.link_chars
    return nodes


def features(n: Node) -> list[str]:
    where = "m:" + "01"[n.marked] + "-+"[n.named]
    if n.text is not None:
        long_ = min(3, len(str(n.chars)) - 1)
        return ["#text", "#" + where, "#chars:%d" % long_, "#stops:%d" % min(2, n.stops)]
    name = "t:" + n.tag if n.tag in KNOWN else "t:?"
    out = [name, "bias", where, name + "-+"[n.named]]
    out += ["c:" + w for w in n.names]
    if n.chars:
        share = n.link_chars / n.chars
        out.append("links:" + ("0" if share == 0 else "1" if share < 0.3 else "2" if share < 0.7 else "3"))
        out.append("chars:%d" % min(4, len(str(n.chars)) - 1))
        out.append("stops:%d" % min(3, int(100 * n.stops / n.chars)))
    return out


KNOWN = BLOCK | VOID | RAW | PLAIN | frozenset("math svg a b i em strong span code cite q small sub sup u s mark time abbr label head font".split())


def kind_of(n: Node) -> str:
    return "text" if n.text is not None else n.tag if n.tag in ("nav", "aside", "footer", "header", "form", "article", "main", "section", "div", "p", "li", "body", "html") else "block" if n.tag in BLOCK else "inline"


class Model:
    """node: weights of features for the state content; edge: per kind of child a 2 x 2 table (parent, child)."""

    def __init__(self, node: dict[str, float], edge: dict[str, np.ndarray]):
        self.node, self.edge = node, edge

    def marginals(self, nodes: list[Node], known: int | None = None) -> tuple[list[float], list]:
        """P(content) of every node; with the pairwise marginals (parent, child) that training needs. known: a node
        that is content for sure."""
        from math import exp, log

        place = {id(n): i for i, n in enumerate(nodes)}
        parent = [place[id(n.parent)] if n.parent is not None else -1 for n in nodes]
        kinds = [kind_of(n) for n in nodes]
        node = self.node
        # log potentials of content against not
        up0, up1 = [0.0] * len(nodes), [sum(node.get(f, 0.0) for f in features(n)) for n in nodes]
        if known is not None:
            up0[known] = -500.0
        message = [None] * len(nodes)
        for i in range(len(nodes) - 1, 0, -1):  # children follow their parents
            e = self.edge.get(kinds[i], ZERO)
            a0, a1 = up0[i], up1[i]
            top = max(a0, a1)
            x0, x1 = exp(a0 - top), exp(a1 - top)
            m0 = log(exp(e[0][0]) * x0 + exp(e[0][1]) * x1) + top
            m1 = log(exp(e[1][0]) * x0 + exp(e[1][1]) * x1) + top
            message[i] = (m0, m1)
            p = parent[i]
            up0[p] += m0
            up1[p] += m1
        out, pairs = [0.0] * len(nodes), [None] * len(nodes)
        belief = [(0.0, 0.0)] * len(nodes)
        belief[0] = (up0[0], up1[0])
        out[0] = 1 / (1 + exp(min(700, max(-700, up0[0] - up1[0]))))
        for i in range(1, len(nodes)):
            e, p = self.edge.get(kinds[i], ZERO), parent[i]
            m0, m1 = message[i]
            c0, c1 = belief[p][0] - m0, belief[p][1] - m1  # the parent without this child
            a0, a1 = up0[i], up1[i]
            j = (c0 + e[0][0] + a0, c0 + e[0][1] + a1, c1 + e[1][0] + a0, c1 + e[1][1] + a1)
            top = max(j)
            w = [exp(x - top) for x in j]
            total = sum(w)
            w = [x / total for x in w]
            pairs[i] = w
            b0, b1 = w[0] + w[2], w[1] + w[3]
            out[i] = b1
            belief[i] = (log(b0 + 1e-300), log(b1 + 1e-300))
        return out, pairs


ZERO = ((0.0, 0.0), (0.0, 0.0))
LEAST = 0.05


def fit(pages: list[tuple[str, list[str]]], *, rounds: int = 12, rate: float = 0.3, decay: float = 1e-3) -> Model:
    """Maximum likelihood from pages whose text runs are labelled: (html, kept texts). An element is content
    if a kept run lies in it. Gradients are observed minus expected counts, the latter from the marginals of the same
    messages."""
    data = []
    for html, kept in pages:
        nodes = parse(html)
        wanted = set(kept)
        good = {}
        for n in reversed(nodes):
            if n.text is not None:
                good[id(n)] = int(" ".join(unescape(n.text).split()) in wanted)
            if n.parent is not None:
                good[id(n.parent)] = good.get(id(n.parent), 0) + good.get(id(n), 0)
        place = {id(n): i for i, n in enumerate(nodes)}
        y = [int(good.get(id(n), 0) > 0) for n in nodes]
        data.append((nodes, y, [place[id(n.parent)] if n.parent is not None else -1 for n in nodes], [kind_of(n) for n in nodes], [features(n) for n in nodes]))
    node, edge = {}, {}
    square: dict = {}
    for _ in range(rounds):
        for nodes, y, parent, kinds, facts in data:
            model = Model(node, edge)
            p, pairs = model.marginals(nodes)
            grad: dict = {}
            for i in range(len(nodes)):
                d = y[i] - p[i]
                for f in facts[i]:
                    grad[f] = grad.get(f, 0.0) + d
                if i:
                    for k in range(4):
                        key = (kinds[i], k)
                        grad[key] = grad.get(key, 0.0) + float(2 * y[parent[i]] + y[i] == k) - pairs[i][k]
            for key, g in grad.items():
                if isinstance(key, tuple):
                    table = edge.setdefault(key[0], [[0.0, 0.0], [0.0, 0.0]])
                    g -= decay * table[key[1] >> 1][key[1] & 1]
                    square[key] = square.get(key, 1e-1) + g * g
                    table[key[1] >> 1][key[1] & 1] += rate * g / square[key] ** 0.5
                else:
                    g -= decay * node.get(key, 0.0)
                    square[key] = square.get(key, 1e-1) + g * g
                    node[key] = node.get(key, 0.0) + rate * g / square[key] ** 0.5
    return Model(node, edge)


def labelled_pages(n: int = 320, seed: int = 5, *, bare: bool | None = None) -> list[tuple[str, list[str]]]:
    """Generated training pages: (html, texts of the content runs). Layouts, names and the order of parts vary."""
    rng = np.random.default_rng(seed)
    pick = lambda x: x[int(rng.integers(len(x)))]
    chance = lambda p: rng.random() < p
    serial = iter(range(10**9))

    def words(lo, hi, stop=True):
        text = " ".join("".join(pick("abcdefghilmnoprstuv") for _ in range(int(rng.integers(2, 9)))) for _ in range(int(rng.integers(lo, hi))))
        return f"{text} x{next(serial)}" + (pick([".", ".", "!", ", y."]) if stop else "")

    def junk():
        links = lambda k: "".join(f'<li><a href="/{i}">{words(1, 3, False)}</a></li>' for i in range(k))
        label = lambda *w: f' {pick(["class", "id"])}="{pick(w)}"'
        k = int(rng.integers(14))
        body = [
            lambda: f"<nav><ul>{links(5)}</ul></nav>",
            lambda: f"<div{label('menu', 'navbar', 'nav main-nav', 'breadcrumb', 'toolbar')}><ul>{links(4)}</ul></div>",
            lambda: f"<div{label('ad', 'ads', 'advert', 'sponsored', 'promo banner', 'advertisement')}>{words(3, 14)}</div>",
            lambda: f"<aside{pick(['', label('sidebar', 'related', 'widget')])}><h3>{words(1, 3, False)}</h3><p>{words(4, 20)}</p><ul>{links(3)}</ul></aside>",
            lambda: f"<div{label('sidebar', 'related', 'widget rail', 'recommended', 'trending')}><h4>{words(1, 3, False)}</h4><p>{words(4, 25)}</p></div>",
            lambda: f"<section{label('comments', 'comment-list', 'disqus', 'discussion')}><h3>{words(1, 3, False)}</h3>" + "".join(f'<{pick(["div", "article", "li"])} class="comment"><b>{words(1, 2, False)}</b><p>{words(4, 30)}</p>' for _ in range(3)) + "</section>",
            lambda: f"<div{label('comments', 'comment', 'reply')}><p>{words(4, 30)}</p><p>{words(4, 30)}</p></div>",
            lambda: f"<form{pick(['', label('search', 'newsletter', 'login')])}><label>{words(1, 4, False)}</label><input><button>{words(1, 2, False)}</button><p>{words(3, 9)}</p></form>",
            lambda: f"<div{label('cookie', 'cookie-notice', 'consent', 'popup', 'gdpr', 'notice', 'alert')}{pick(['', ' role=\"alert\"'])}><p>{words(5, 20)}</p><button>{words(1, 2, False)}</button></div>",
            lambda: f"<div{label('share', 'social', 'tags', 'meta', 'author bio', 'pagination', 'newsletter', 'subscribe')}>{words(2, 12, False)} <a href=\"/\">{words(1, 2, False)}</a></div>",
            lambda: f"<div hidden>{words(4, 20)}</div>" if chance(0.5) else f'<div style="display:none"><p>{words(4, 20)}</p></div>',
            lambda: f"<figure{label('promo', 'ad')}><figcaption>{words(2, 8)}</figcaption></figure>",
            lambda: f"<form><textarea>{words(3, 9)}</textarea></form><svg><text>{words(1, 3, False)}</text></svg>",
            lambda: f"<noscript>{words(3, 6)}</noscript><select><option>{words(1, 2, False)}</option></select>",
        ][k]
        return body()

    out = []
    for _ in range(n):
        kept = []

        small = chance(0.2)  # pages of a few words

        def keep(lo, hi, stop=True):
            text = words(lo, hi, stop)
            kept.append(text.split()[0] if small and chance(0.8) else text)
            return kept[-1]

        def inner():
            k = int(rng.integers(12))
            if k == 11:
                return f"<p>{keep(2, 9, False)} <math><mi>{keep(1, 2, False)}</mi> <mo>{keep(1, 2, False)}</mo></math> {keep(2, 12)}</p>"
            if k < 5:
                return f"<p>{keep(1, 80, chance(0.8))}" + pick(["</p>", "</p>", ""])
            if k == 5:
                return f"<h{pick('234')}>{keep(1, 8, False)}</h2>"
            if k == 6:
                return f"<p>{keep(3, 30, False)} <{(t := pick(['b', 'i', 'em', 'strong', 'code']))}>{keep(1, 4, False)}</{t}> {keep(2, 30)}</p>"
            if k == 7:
                return f"<{(t := pick(['ul', 'ol']))}>" + "".join(f"<li>{keep(2, 12)}</li>" for _ in range(3)) + f"</{t}>"
            if k == 8:
                return f"<blockquote>{keep(3, 30)}</blockquote>" + (f"<pre>{keep(2, 9, False)}</pre>" if chance(0.3) else "")
            if k == 9:
                return "<table><tr>" + "".join(f"<td>{keep(1, 5, False)}</td>" for _ in range(3)) + "</tr></table>" if chance(0.5) else f"<figure><figcaption>{keep(2, 9)}</figcaption></figure>"
            return f"<p><b>{keep(2, 30, chance(0.8))}<br><p>{keep(2, 60, chance(0.8))} <a href='/x'>{keep(1, 3, False)}</a> {keep(1, 20)}</p>"

        parts = [f"<h1>{keep(2, 9, False)}</h1>"] if chance(0.8) else []
        plain = chance(0.4) if bare is None else bare  # nothing names the content: plain boxes, table cells, the body itself, a fragment
        for _ in range(1 if chance(0.15) else int(rng.integers(1, 9))):
            parts.append(inner())
            if chance(0.08):
                parts.append(junk())
        body = "".join(parts)
        if chance(0.15):
            body = f"<section>{body}</section>"
        if chance(0.15):
            body = f"<div>{body}</div>"
        head, tail = pick([("<article>", "</article>")] * 4 + [("<main>", "</main>"), ("<main><article>", "</article></main>"), ('<div class="content">', "</div>"), ('<div id="main-content">', "</div>"), ('<div class="post entry-content">', "</div>"), ('<div class="story-body">', "</div>"), ('<article class="post">', "</article>"), ('<div itemprop="articleBody">', "</div>"), ('<div role="main">', "</div>")])
        if plain:
            head, tail = pick([("", ""), ("<div>", "</div>"), ('<div class="col">', "</div>"), ('<div id="wrapper"><div class="col">', "</div></div>"), ('<div class="page"><div>', "</div></div>"), ("<section>", "</section>"), ("<table><tr><td>", "</td></tr></table>")])
        if chance(0.2) and "article" in head:
            head += f"<header>{pick(['', '<p class=\"meta\">' + words(2, 5, False) + '</p>'])}</header>"
        before = [junk() for _ in range(int(rng.integers(0, 4)))]
        after = [junk() for _ in range(int(rng.integers(0, 4)))]
        top = pick(["", f"<header><div>{words(1, 4, False)}</div></header>", f"<div class=\"header\"><p>{words(1, 6, False)}</p></div>", f"<header><h2>{words(1, 3, False)}</h2><p>{words(2, 9)}</p></header>"])
        foot = pick(["", f"<footer>&copy; {words(2, 9)}</footer>", f"<footer><p>{words(2, 9)}</p><ul><li><a href='/'>{words(1, 2, False)}</a></li></ul></footer>", f"<div class=\"footer\"><p>{words(2, 9)}</p></div>"])
        page = f"<!DOCTYPE html><html><head><meta charset=\"utf-8\"><title>{words(2, 8)}</title><style>p{{}}</style><script>1</script></head><body>{top}{''.join(before)}<!-- x -->{head}{body}{tail}{''.join(after)}{foot}" + pick(["</body></html>", ""])
        if chance(0.2):
            page = page.replace("<body>", '<body><div id="wrapper">')
        if chance(0.2):  # all there is
            page = pick(["{}", "<body>{}</body>", "<article>{}</article>", "<div>{}</div>", "<body><div>{}</div></body>", "<html><body><div><div>{}</div></div></body></html>"]).format(body)
        out.append((page, kept))
    return out


@lru_cache(maxsize=1)
def default_model() -> Model:
    return fit(labelled_pages())


def main_text(html: str | None, model: Model) -> str:
    if not html:
        return ""
    nodes = parse(html)
    keep, _ = model.marginals(nodes)
    runs = [i for i, n in enumerate(nodes) if n.text is not None]
    best = max(runs, key=lambda i: keep[i], default=None)
    if best is not None and LEAST <= keep[best] < 0.5:
        keep, _ = model.marginals(nodes, known=best)
    blocks, run, owner = [], [], None

    def flush():
        text = " ".join("".join(run).split())
        if text:
            blocks.append(text)
        run.clear()

    # text runs of one block that no other block's start or text separates are one block of the result
    for n, p in zip(nodes, keep):
        if n.space:
            run.append(" ")
        if n.text is None:
            if n.tag in BLOCK:
                flush()
                owner = None
            elif n.tag == "br":
                run.append(" ")
            continue
        own = n.block
        if own is not owner:
            flush()
            owner = own
        if p >= 0.5:
            run.append(unescape(n.text))
    flush()
    return "\n\n".join(blocks)


def extract(pages: DataFrame, model: Model | None = None) -> DataFrame:
    """page_id, url, text, n_chars for every row of ``pages`` (page_id, url, html)."""
    model = model or default_model()
    shared = pages.sparkSession.sparkContext.broadcast((model.node, model.edge))

    def run(batches):
        own = Model(*shared.value)
        for b in batches:
            texts = [main_text(h.as_py(), own) for h in b.column("html")]
            yield pa.RecordBatch.from_arrays([b.column("page_id"), b.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), "html")
    return arrow_map(rows, run, "page_id long, url string, text string, n_chars long")
