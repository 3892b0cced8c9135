"""Main text of web pages by a tree-structured graphical model.

Each block element of a page is a node with a hidden state, article or not.  Node
potentials are log-linear in features of the element and of the nearest element
around it that tells its use; edge potentials tie a child to its parent by the
child's kind and the magnitude of the number of siblings, as many children that each
say a little must not outweigh what the parent says itself.  Sum-product messages go
up the tree and down again and give exact marginals.  The weights are trained on labelled pages, made by
a generator that draws layouts at random and knows what it put where.
"""

from __future__ import annotations

import html as entities
import random
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Element kinds of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style title textarea template iframe select button option".split())
HEAD = frozenset("html head base link meta script style title noscript template".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var br img wbr math svg object noscript".split())
MATH = frozenset("mi mn mo ms mtext mrow mfrac msqrt mroot msup msub msubsup mover munder munderover mmultiscripts mstyle mpadded mphantom mspace menclose mtable mtr mtd semantics annotation annotation-xml g text tspan textpath".split())
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
KINDS = ("html", "body", "div", "section", "article", "main", "p", "h1", "h2", "h3", "h4", "h5", "h6", "ul", "ol", "li", "dl", "dt", "dd", "table", "tr", "td", "th", "blockquote", "pre", "figure", "figcaption", "nav", "header", "footer", "aside", "form", "menu", "address", "details", "dialog", "fieldset", "other")
# Words of class, id and role, in groups that mean the same.
HINTS = (
    ("nav", "navbar", "navigation", "menu", "breadcrumb", "breadcrumbs", "pagination", "pager", "toc", "skip"),
    ("header", "masthead", "topbar", "branding", "logo"),
    ("footer", "copyright", "colophon", "legal", "contentinfo"),
    ("sidebar", "side", "aside", "widget", "widgets", "rail", "complementary"),
    ("ad", "ads", "adv", "advert", "advertisement", "adbox", "sponsor", "sponsored", "promo", "promotion", "banner", "adsense", "teaser"),
    ("cookie", "cookies", "consent", "notice", "alert", "gdpr", "popup", "modal", "overlay", "warning", "message", "dialog", "disclaimer"),
    ("comment", "comments", "commentlist", "reply", "replies", "respond", "disqus", "discussion", "reader", "feedback"),
    ("share", "social", "sharing", "follow", "tweet", "like"),
    ("related", "recommended", "more", "popular", "trending", "newsletter", "subscribe", "signup", "login", "search", "form", "tags", "author", "bio", "meta", "byline"),
    ("article", "content", "main", "post", "entry", "body", "story", "text", "page", "prose"),
)
_HINT = {w: i for i, group in enumerate(HINTS) for w in group}

_TOKEN = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*(?:>|$)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|$)", re.S)
_ATTR = re.compile(r"""\b(class|id|role|hidden|aria-hidden)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+)))?""", re.I)
_WORDS = re.compile(r"[a-z]+")


class Node:
    __slots__ = ("attrs", "children", "items", "linked", "parent", "tag")

    def __init__(self, tag: str, attrs: str, parent: int):
        self.tag, self.attrs, self.parent = tag, attrs, parent
        self.children: list[int] = []
        self.items: list[tuple[int, str]] = []  # (order, text)
        self.linked = 0


def parse(page: str) -> list[Node]:
    """Block elements as a tree (parents first); inline markup only leaves its text, a block's text keeps page order."""
    nodes = [Node("html", "", -1)]
    stack = [0]
    order = links = at = 0
    head = False  # inside the head; text or an element that cannot be there ends it

    def text(chunk: str) -> None:
        nonlocal order, head
        head = head and not chunk.strip()
        if chunk and not head:
            node = nodes[stack[-1]]
            node.items.append((order, chunk))
            if links:
                node.linked += len(chunk.strip())

    while True:
        m = _TOKEN.search(page, at)
        if m is None:
            text(page[at:])
            break
        text(page[at : m.start()])
        at = m.end()
        if m[2] is None:
            continue
        tag = m[2].lower()
        if not m[1]:
            head = head and tag in HEAD
            if tag in RAW and not m[3].rstrip().endswith("/"):
                end = _end_of(tag, page, at)
                close = page.find(">", end)
                at = len(page) if close < 0 else close + 1
                continue
            if tag == "br" or tag == "hr":
                text(" ")
            if tag == "a":
                links += 1
            if tag == "xmp":  # its markup is text
                end = _end_of(tag, page, at)
                nodes[stack[-1]].items.append((order, page[at:end].replace("&", "&amp;")))
                at = end
                continue
            if tag in INLINE or tag in MATH or tag in VOID:
                continue
            if tag in ("html", "head") or (tag == "body" and len(nodes) > 1 and nodes[stack[-1]].tag == "body"):
                head = head or (tag == "head" and len(nodes) == 1)
                continue
            if tag in CLOSES_P and nodes[stack[-1]].tag == "p":
                stack.pop()
            if tag == "li":
                _close(nodes, stack, ("li",), ("ul", "ol", "menu"))
            elif tag in ("dt", "dd"):
                _close(nodes, stack, ("dt", "dd"), ("dl",))
            elif tag in ("td", "th"):
                _close(nodes, stack, ("td", "th"), ("tr", "table"))
            elif tag == "tr":
                _close(nodes, stack, ("tr",), ("table", "tbody"))
            order += 1
            nodes.append(Node(tag, m[3], stack[-1]))
            nodes[stack[-1]].children.append(len(nodes) - 1)
            stack.append(len(nodes) - 1)
            links = 0
        else:
            head = head and tag not in ("head", "body", "html")
            if tag == "a":
                links = max(0, links - 1)
            if tag in INLINE or tag in MATH or tag in VOID:
                continue
            for depth in range(len(stack) - 1, 0, -1):
                if nodes[stack[depth]].tag == tag:
                    del stack[depth:]
                    order += 1
                    links = 0
                    break
    return nodes


@lru_cache(maxsize=64)
def _end_tag(tag: str) -> re.Pattern:
    return re.compile(f"</{tag}(?![a-z0-9])", re.I | re.A)


def _end_of(tag: str, page: str, at: int) -> int:
    """Where the element's end tag starts, in either case; the end of the page without one."""
    m = _end_tag(tag).search(page, at)
    return m.start() if m else len(page)


def _close(nodes: list[Node], stack: list[int], tags: tuple[str, ...], stop: tuple[str, ...]) -> None:
    for depth in range(len(stack) - 1, 0, -1):
        tag = nodes[stack[depth]].tag
        if tag in stop:
            return
        if tag in tags:
            del stack[depth:]
            return


_KIND = {k: i for i, k in enumerate(KINDS)}
_SIZES = (1, 20, 60, 150, 400, 1200)
#: What an element is to its parent: its first hint, else its tag.
N_USES = len(HINTS) + len(KINDS)
#: Tags that tell the use of what they hold.
TELLING = frozenset("nav header footer aside form menu dialog fieldset article main address details".split())
N_FEATURES = len(KINDS) + len(HINTS) + len(_SIZES) + 1 + 6 + N_USES
#: Magnitudes (powers of 4) of the number of siblings; no page has more.
N_MANY = 24
N_EDGES = N_USES * N_MANY


@lru_cache(maxsize=65536)
def _hints(attrs: str) -> tuple[tuple[int, ...], bool]:
    found, hidden = set(), False
    for m in _ATTR.finditer(attrs):
        name = m[1].lower()
        if name == "hidden" or name == "aria-hidden":
            hidden = True
            continue
        for w in _WORDS.findall((m[2] or m[3] or m[4] or "").lower()):
            if w in _HINT:
                found.add(_HINT[w])
    return tuple(sorted(found)), hidden


def features(nodes: list[Node]) -> tuple[list[list[int]], list[int]]:
    """Active binary features and the edge kind of every node."""
    size, linked = [0] * len(nodes), [0] * len(nodes)
    for i in range(len(nodes) - 1, -1, -1):
        own = nodes[i]
        size[i] += sum(len(t.strip()) for _, t in own.items)
        linked[i] += own.linked
        if own.parent >= 0:
            size[own.parent] += size[i]
            linked[own.parent] += linked[i]
    out, edge, within = [], [], []
    base = len(KINDS) + len(HINTS)
    for i, node in enumerate(nodes):
        kind = _KIND.get(node.tag, len(KINDS) - 1)
        hints, hidden = _hints(node.attrs)
        f = [kind, *(len(KINDS) + h for h in hints)]
        f.append(base + sum(size[i] >= s for s in _SIZES))
        share = linked[i] / size[i] if size[i] else 0.0
        at = base + len(_SIZES) + 1
        if share > 0.8:
            f.append(at)
        elif share > 0.3:
            f.append(at + 1)
        if hidden:
            f.append(at + 2)
        if any(h == len(HINTS) - 1 for h in hints) and len(hints) == 1:
            f.append(at + 3)
        if node.children:
            f.append(at + 4)
        f.append(at + 5)
        use = hints[0] if hints else len(HINTS) + kind
        around = within[node.parent] if node.parent >= 0 else -1  # the use of the nearest telling element around
        if around >= 0:
            f.append(at + 6 + around)
        within.append(use if hints or node.tag in TELLING else around)
        out.append(f)
        siblings = len(nodes[node.parent].children) if node.parent >= 0 else 1
        edge.append(use * N_MANY + (siblings.bit_length() - 1) // 2)
    return out, edge


def marginals(nodes: list[Node], feats: list[list[int]], edge: list[int], w: np.ndarray, e: np.ndarray) -> tuple[list[float], list[tuple]]:
    """P(article) of each node, and of each edge the joint table (parent, child) as four numbers, by sum-product."""
    n = len(nodes)
    used = sorted(set(edge))
    weights, ties = w.tolist(), dict(zip(used, np.exp(e[used]).tolist(), strict=True))
    unary = [2.718281828459045 ** max(-30.0, min(30.0, sum(weights[k] for k in f))) for f in feats]  # state 1 against 0
    up0, up1 = [1.0] * n, [1.0] * n  # product of messages from the children
    m0, m1 = [1.0] * n, [1.0] * n
    for i in range(n - 1, 0, -1):
        b0, b1 = up0[i], up1[i] * unary[i]
        (t00, t01), (t10, t11) = ties[edge[i]]
        x0, x1 = t00 * b0 + t01 * b1, t10 * b0 + t11 * b1
        z = x0 + x1
        p = nodes[i].parent
        m0[i], m1[i] = x0 / z, x1 / z
        up0[p] *= m0[i]
        up1[p] *= m1[i]
        z = up0[p] + up1[p]
        up0[p] /= z
        up1[p] /= z
    down0, down1 = [1.0] * n, [1.0] * n
    belief, joint = [0.0] * n, [(0.0, 0.0, 0.0, 0.0)] * n
    for i in range(n):
        b0, b1 = up0[i] * down0[i], up1[i] * unary[i] * down1[i]
        belief[i] = b1 / (b0 + b1)
        for c in nodes[i].children:
            c0, c1 = b0 / max(m0[c], 1e-300), b1 / max(m1[c], 1e-300)
            z = c0 + c1
            c0, c1 = c0 / z, c1 / z
            (t00, t01), (t10, t11) = ties[edge[c]]
            d0, d1 = c0 * t00 + c1 * t10, c0 * t01 + c1 * t11
            z = d0 + d1
            down0[c], down1[c] = d0 / z, d1 / z
            a0, a1 = up0[c], up1[c] * unary[c]
            q = (c0 * t00 * a0, c0 * t01 * a1, c1 * t10 * a0, c1 * t11 * a1)
            s = sum(q)
            joint[c] = tuple(v / s for v in q)
    return belief, joint


_SPACE = re.compile(r"\s+")


def blocks(nodes: list[Node]) -> list[tuple[int, str]]:
    """Runs of text in page order with their node; references decoded, white space made single."""
    pieces: list[tuple[int, int, str]] = []
    for i, node in enumerate(nodes):
        run: list[str] = []
        last = None
        for order, t in node.items:
            if last is not None and order != last:
                pieces.append((last, i, "".join(run)))
                run = []
            run.append(t)
            last = order
        if run:
            pieces.append((last, i, "".join(run)))
    pieces.sort(key=lambda x: x[0])
    out = []
    for _, i, t in pieces:
        t = " ".join(entities.unescape(t).split())
        if t:
            out.append((i, t))
    return out


class Model:
    def __init__(self, w: np.ndarray, e: np.ndarray):
        self.w, self.e = w, e

    def text(self, page: str) -> str:
        nodes = parse(page)
        feats, edge = features(nodes)
        belief, _ = marginals(nodes, feats, edge, self.w, self.e)
        return " ".join(t for i, t in blocks(nodes) if belief[i] > 0.5)


def labelled_pages(n: int, seed: int = 7) -> list[tuple[list[Node], list[int]]]:
    """Random layouts with the state of every block: boilerplate elements carry a mark that the parser hands back."""
    rng = random.Random(seed)
    out = []
    for _ in range(n):
        nodes = parse(_layout(rng))
        labels = []
        for node in nodes:
            own = "data-x" in node.attrs
            labels.append(0 if own or (node.parent >= 0 and labels[node.parent] == 0) else 1)
            node.attrs = node.attrs.replace("data-x", "")
        out.append((nodes, labels))
    return out


def _layout(rng: random.Random) -> str:
    def prose(lo: int, hi: int) -> str:
        return " ".join("".join(rng.choice("abcdefghilmnorstu") for _ in range(rng.randint(2, 9))) for _ in range(rng.randint(lo, hi))) + "."

    def attrs(group: int, chance: float) -> str:
        if rng.random() > chance:
            return ""
        word = rng.choice(HINTS[group])
        word = rng.choice([word, f"{word}-{rng.choice(['box', 'wrap', 'list', 'area', 'item'])}", f"site-{word}", f"{word} x{rng.randint(1, 9)}"])
        return f' {rng.choice(["class", "class", "id", "role"])}="{word}"'

    def links(lo: int, hi: int) -> str:
        return "".join(f'<li><a href="#">{prose(1, 3)}</a></li>' for _ in range(rng.randint(lo, hi)))

    def junk(group: int, tags: list[str], inner: str, sure: float = 0.95) -> str:
        tag = rng.choice(tags)
        chance = 0.4 if tag in ("nav", "header", "footer", "aside", "form") else sure + 0.05
        return f"<{tag}{attrs(group, chance)} data-x>{inner}</{tag}>"

    def some_text() -> str:
        return rng.choice([prose(2, 12), f"<p>{prose(3, 25)}</p>", f"<p>{prose(3, 25)}</p><p>{prose(3, 40)}</p>", f"<h3>{prose(1, 4)}</h3><ul>{links(2, 6)}</ul>", f"<h2>{prose(1, 4)}</h2><p>{prose(4, 30)}</p>", f"<div>{prose(2, 15)}</div>"])

    nav = lambda: junk(0, ["nav", "nav", "div", "ul"], rng.choice([f"<ul>{links(3, 9)}</ul>", links(3, 9), "".join(f'<a href="#">{prose(1, 2)}</a> ' for _ in range(5))]))
    header = lambda: junk(1, ["header", "header", "div"], rng.choice([f"<h1>{prose(1, 5)}</h1>", prose(1, 8), f"<p>{prose(1, 10)}</p>", f'<a href="#">{prose(1, 4)}</a>', f"<div>{prose(1, 5)}</div>{nav()}"]))
    footer = lambda: junk(2, ["footer", "footer", "div"], rng.choice([prose(2, 20), f"<p>{prose(2, 30)}</p>", f"<ul>{links(2, 7)}</ul>", f"<p>{prose(2, 9)}</p><p>{prose(2, 9)}</p>"]))
    side = lambda: junk(3, ["aside", "aside", "div", "section"], some_text())
    ad = lambda: junk(4, ["div", "div", "aside", "section", "p"], some_text())
    notice = lambda: junk(5, ["div", "div", "section", "aside", "p", "dialog"], some_text())
    share = lambda: junk(rng.choice([7, 8]), ["div", "section", "ul"], some_text())
    form = lambda: junk(8, ["form", "form", "div"], rng.choice([f"<label>{prose(1, 3)}</label><input>", f"<p>{prose(2, 9)}</p><input>", f"<fieldset><p>{prose(1, 9)}</p></fieldset>"]))

    def comments() -> str:
        one = lambda: rng.choice([f"<p>{prose(4, 60)}</p>", f"<div>{prose(4, 60)}</div>", f"<li>{prose(4, 60)}</li>", f"<article><h4>{prose(1, 3)}</h4><p>{prose(4, 60)}</p></article>", f'<div class="{rng.choice(HINTS[6])}"><p>{prose(4, 60)}</p></div>'])
        return junk(6, ["section", "div", "div", "ol", "ul", "aside"], rng.choice(["", f"<h3>{prose(1, 3)}</h3>"]) + "".join(one() for _ in range(rng.randint(1, 6))), 1.0)

    def block() -> str:
        return rng.choice([
            lambda: f"<p>{prose(1, 120)}</p>", lambda: f"<p>{prose(1, 12)}</p>", lambda: f"<p><b>{prose(1, 60)}<br><p>{prose(10, 80)}</p>", lambda: f"<p>{prose(8, 40)} <a href='#'>{prose(1, 4)}</a> {prose(4, 20)}</p>",
            lambda: f"<h{(h := rng.randint(2, 4))}>{prose(1, 8)}</h{h}>", lambda: "<ul>" + "".join(f"<li>{prose(1, 25)}</li>" for _ in range(rng.randint(1, 6))) + "</ul>", lambda: "<ol>" + "".join(f"<li><p>{prose(2, 25)}</p></li>" for _ in range(rng.randint(1, 6))) + "</ol>",
            lambda: f"<blockquote>{rng.choice([prose(4, 40), f'<p>{prose(4, 40)}</p>'])}</blockquote>", lambda: f"<pre>{prose(4, 30)}</pre>", lambda: f"<figure><img src=x><figcaption>{prose(2, 12)}</figcaption></figure>",
            lambda: "<table>" + "".join("<tr>" + "".join(f"<td>{prose(1, 3)}</td>" for _ in range(3)) + "</tr>" for _ in range(3)) + "</table>", lambda: f"<div>{prose(3, 80)}</div>", lambda: f"<div><p>{prose(3, 80)}</p></div>", lambda: f"<section><h2>{prose(1, 5)}</h2><p>{prose(3, 80)}</p></section>", lambda: f"<dl><dt>{prose(1, 3)}</dt><dd>{prose(2, 20)}</dd></dl>",
        ])()

    parts = [f"<h1>{prose(1, 10)}</h1>"] if rng.random() < 0.8 else []
    brief = rng.random() < 0.4
    plain, top = rng.random() < 0.5, rng.choice([3, 8, 25, 60, 120])
    for _ in range(rng.choice([1, 2, 4, 8, 12, 25, 60]) if not brief else rng.choice([0, 1, 1, 2])):
        parts.append(f"<p>{prose(1, top)}</p>" if plain and not brief else block() if not brief else f"<p>{prose(1, rng.choice([4, 12, 25]))}</p>")
        if rng.random() < (0.02 if plain else 0.12):
            parts.append(rng.choice([ad, share, side, form, nav, notice])())
    if rng.random() < 0.1:
        parts.append(comments())
    body = "".join(parts)
    shell = rng.random()
    if shell < 0.5:
        body = f"<article{attrs(9, 0.3)}>{body}</article>"
    elif shell < 0.7:
        body = f"<main{attrs(9, 0.4)}>{body}</main>"
    elif shell < 0.95:
        body = f"<div{attrs(9, 0.9)}>{body}</div>"
    if rng.random() < 0.3:
        body = f"<main>{body}</main>"
    before = [f() for f, p in ((notice, 0.3), (header, 0.6), (nav, 0.7), (ad, 0.5), (form, 0.2), (side, 0.2)) if rng.random() < p]
    after = [f() for f, p in ((share, 0.2), (comments, 0.5), (side, 0.4), (ad, 0.3), (form, 0.2), (notice, 0.2), (footer, 0.8)) if rng.random() < p]
    if rng.random() < 0.1:
        before, after = [], []
    rng.shuffle(before)
    inner = "".join(before) + body + "".join(after)
    if rng.random() < 0.3:
        inner = f"<div{rng.choice(['', ' class=wrapper', ' id=page', ' class=container'])}>{inner}</div>"
    return f"<html><body>{inner}</body></html>"


@lru_cache(maxsize=2)
def trained(n: int = 500, epochs: int = 25, seed: int = 7) -> Model:
    """Likelihood ascent: observed minus expected features, the latter from the messages' marginals."""
    pages = [(nodes, labels, *features(nodes)) for nodes, labels in labelled_pages(n, seed)]
    w, e = np.zeros(N_FEATURES), np.zeros((N_EDGES, 2, 2))
    sw, se = np.full_like(w, 1e-2), np.full_like(e, 1e-2)
    rng = random.Random(seed)
    for _ in range(epochs):
        rng.shuffle(pages)
        for start in range(0, len(pages), 10):
            gw, ge = np.zeros_like(w), np.zeros_like(e)
            for nodes, labels, feats, edge in pages[start : start + 10]:
                belief, joint = marginals(nodes, feats, edge, w, e)
                for i, f in enumerate(feats):
                    gap = labels[i] - belief[i]
                    if abs(gap) > 1e-4:
                        for k in f:
                            gw[k] += gap
                    if i:
                        t = ge[edge[i]]
                        t[labels[nodes[i].parent], labels[i]] += 1
                        j = joint[i]
                        t[0, 0] -= j[0]
                        t[0, 1] -= j[1]
                        t[1, 0] -= j[2]
                        t[1, 1] -= j[3]
            gw -= 0.02 * w
            ge -= 0.02 * e
            sw += gw * gw
            se += ge * ge
            w += 0.3 * gw / np.sqrt(sw)
            e += 0.3 * ge / np.sqrt(se)
    return Model(w, e)


def extract(pages: DataFrame) -> DataFrame:
    """``page_id, url, text, n_chars`` for every row of ``pages`` (``page_id, url, html``).

    Null or empty html gives an empty text, as does a page without an article part;
    text without any markup is its own article.  Rows that repeat are read each;
    other columns are ignored; an empty table gives an empty result.
    """
    model = trained()
    sent = pages.sparkSession.sparkContext.broadcast((model.w, model.e))

    def read(batches):
        m = Model(*sent.value)
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                texts = [m.text(h) if h else "" for h in part.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), "html").mapInArrow(read, "page_id long, url string, text string, n_chars long")
