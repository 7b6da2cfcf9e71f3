"""Main text of web pages: boosted trees over DOM nodes, decoded along the tree."""

from __future__ import annotations

import functools
import html
import math
import random
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.llm._common import table, text_chunks

#: Made pages that the trees learn from, trees, their depth and step.
TRAIN_PAGES, TREES, DEPTH, STEP = 400, 40, 4, 0.2

# Fixed values of HTML: element classes that decide how text is cut into blocks.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style template iframe svg textarea select title annotation annotation-xml".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr math semantics mfrac mi mn mo mover mpadded mphantom mroot mrow ms mspace msqrt mstyle msub msubsup msup mtext munder munderover".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split())
CLOSES_OWN = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",), "thead": ("tr", "td", "th"), "tbody": ("thead", "tr", "td", "th"), "tfoot": ("tbody", "tr", "td", "th")}
SCOPES = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("table",), "th": ("table",), "thead": ("table",), "tbody": ("table",), "tfoot": ("table",)}

_TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(?P<close>/?)(?P<tag>[a-zA-Z][^\s/>]*)(?P<rest>(?:[^>"']|"[^"]*"|'[^']*')*+)>|<(?P<close2>/?)(?P<tag2>[a-zA-Z][^\s/>]*)(?P<rest2>[^>]*)(?:>|\Z)""", re.S)
_ATTR = re.compile(r"""(?:^|[\s/"'])(class|id|role|itemprop|aria-label|hidden)\s*(?:=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""", re.I | re.S)
_PARTS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")
#: Ends of raw elements; an end tag may hold white space and attributes, and the page may end inside one.
_RAW_ENDS = {tag: re.compile(rf"</{tag}(?:[\s/][^>]*)?(?:>|\Z)", re.I) for tag in RAW}

#: Attribute tokens, by what they usually hold.
TOKENS = {
    "content": "article body content entry main post story text".split(),
    "menu": "breadcrumb breadcrumbs menu nav navbar navigation pagination pager toc toolbar tabs skip".split(),
    "edge": "banner foot footer header masthead top bottom copyright legal credits".split(),
    "side": "aside related recommended rail side sidebar widget popular trending tags share social".split(),
    "advert": "ad ads adv advert advertisement advertising adsense promo promoted promotion sponsor sponsored".split(),
    "notice": "alert consent cookie cookies gdpr modal notice notification overlay popup privacy subscribe subscription newsletter signup login".split(),
    "talk": "comment comments discussion disqus replies reply respond response responses thread".split(),
}
_GROUPS = {t: g for g, ts in enumerate(TOKENS.values()) for t in ts}
_TAG_KINDS = {"article": 0, "main": 0, "nav": 1, "menu": 1, "header": 2, "footer": 2, "aside": 3, "form": 4, "fieldset": 4, "button": 4, "p": 5, "h1": 6, "h2": 6, "h3": 6, "h4": 6, "h5": 6, "h6": 6, "ul": 7, "ol": 7, "dl": 7, "li": 8, "dt": 8, "dd": 8, "div": 9, "section": 9, "body": 10, "html": 10, "#root": 10, "head": 11, "blockquote": 12, "pre": 12, "table": 12, "td": 12, "figure": 12, "dialog": 4}


class Node:
    """A block element (text None) or a run of text inside one."""

    __slots__ = ("depth", "groups", "hidden", "inside", "kids", "link", "parent", "tag", "text")

    def __init__(self, tag: str, parent: Node | None, text: str | None = None, link: int = 0):
        self.tag, self.parent, self.text, self.link = tag, parent, text, link
        self.kids: list[Node] = []
        self.groups, self.hidden = 0, False
        self.depth = parent.depth + 1 if parent else 0
        if parent:
            parent.kids.append(self)
        self.inside = 0


def _attributes(node: Node, rest: str) -> None:
    for m in _ATTR.finditer(rest):
        name, value = m[1].lower(), m[2] or m[3] or m[4] or ""
        if name == "hidden":
            node.hidden = True
        for part in _PARTS.findall(value):
            group = _GROUPS.get(part.lower())
            if group is not None:
                node.groups |= 1 << group


def parse_blocks(page: str) -> Node:
    """The tree of block elements and text runs of a page; implied ends are closed, scripts, styles and comments are gone.

    Inline elements only add to the run that is open, so a run is a block's
    text between block boundaries, with line breaks as white space.
    """
    root = Node("#root", None)
    node, run, link, links, at = root, [], 0, 0, 0
    stack: list[tuple[str, Node]] = []

    def flush() -> None:
        nonlocal run, link
        if run:
            text = " ".join(html.unescape("".join(run)).split())
            if text:
                Node("#text", node, text, link)
            run, link = [], 0

    def pop_to(place: int) -> None:
        nonlocal node, links
        if any(t not in INLINE for t, _ in stack[place:]):
            flush()
        for tag, before in reversed(stack[place:]):
            links -= tag == "a"
            node = before
        del stack[place:]

    end = len(page)
    while at < end:
        m = _TOKEN.search(page, at)
        piece = page[at : m.start() if m else end]
        if piece:
            run.append(piece)
            if links:
                link += len(piece)
        if not m:
            break
        at = m.end()
        tag = m["tag"] or m["tag2"]
        if not tag or (m["tag2"] and not m[0].endswith(">")):
            continue
        tag, closing, rest = tag.lower(), m["close"] or m["close2"], m["rest"] or m["rest2"] or ""
        if closing:
            place = next((i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == tag), None)
            if place is not None and not (tag in INLINE and any(t not in INLINE for t, _ in stack[place:])):
                pop_to(place)
            elif tag == "p":
                flush()
            elif place is not None and tag == "a":
                stack[place] = ("span", stack[place][1])
                links -= 1
            continue
        if tag in RAW:
            if tag != "svg" or not rest.endswith("/"):
                stop = _RAW_ENDS[tag].search(page, at)
                at = stop.end() if stop else end
            continue
        if tag == "br":
            run.append("\n")
            continue
        if tag in CLOSES_P:
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] == "p":
                    pop_to(i)
                    break
                if stack[i][0] not in INLINE:
                    break
        for own in CLOSES_OWN.get(tag, ()):
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] == own:
                    pop_to(i)
                    break
                if stack[i][0] in SCOPES.get(tag, ()):
                    break
        if tag in VOID:
            if tag not in INLINE:
                flush() if tag == "hr" else None
            continue
        if tag in INLINE:
            stack.append((tag, node))
            links += tag == "a"
            continue
        flush()
        stack.append((tag, node))
        node = Node(tag, node)
        if rest:
            _attributes(node, rest)
    flush()
    return root


N_FEATURES = 34


def node_features(root: Node) -> tuple[list[Node], np.ndarray]:
    """Nodes in page order and their features: own and subtree text, link share and density, tag, tokens, depth, siblings, ancestors."""
    nodes: list[Node] = []
    todo = [root]
    while todo:
        n = todo.pop()
        nodes.append(n)
        todo.extend(reversed(n.kids))
    size: dict[int, list[float]] = {}
    for n in reversed(nodes):
        own = [len(n.text), n.link, 1, 1, n.text.count(".") + n.text.count("!") + n.text.count("?")] if n.text is not None else [0, 0, 0, 1, 0]
        for k in n.kids:
            for i, x in enumerate(size[id(k)]):
                own[i] += x
        size[id(n)] = own
    whole = size[id(root)]
    total = max(1.0, whole[0])
    rows, before = np.zeros((len(nodes), N_FEATURES), np.float32), 0.0
    heads_seen = False
    for i, n in enumerate(nodes):
        up = n.parent
        n.inside = (up.inside | up.groups | (1 << (8 + _TAG_KINDS.get(up.tag, 13)))) if up else 0
        if up is not None and up.hidden:
            n.hidden = True
        chars, link, runs, tags, stops = size[id(n)]
        siblings = up.kids if up else [n]
        around = size[id(up)] if up else whole
        kind = _TAG_KINDS.get(n.tag if n.text is None else up.tag, 13)
        ins = n.inside
        rows[i, :20] = (
            math.log1p(chars), link / max(1.0, chars), chars / max(1.0, tags), chars / total, runs, stops / max(1.0, runs), kind, n.depth, len(siblings), chars / max(1.0, around[0]),
            around[1] / max(1.0, around[0]), before / total, n.text is not None, n.hidden, heads_seen, around[0] / max(1.0, around[3]), n.groups.bit_count(), (up.groups if up else 0).bit_count(), sum(k.tag == n.tag for k in siblings[:64]), around[4] / max(1.0, around[2]),
        )
        for g in range(7):
            rows[i, 20 + g] = 2.0 if n.groups >> g & 1 else float(ins >> g & 1)
        for j, k in enumerate((0, 1, 2, 3, 4, 11)):
            rows[i, 27 + j] = 2.0 if n.text is None and kind == k else float(ins >> (8 + k) & 1)
        rows[i, 33] = len(n.kids)
        if n.text is not None:
            before += chars
        heads_seen = heads_seen or n.tag == "h1"
    return nodes, rows


class Trees:
    """Boosted regression trees of fixed depth under logistic loss, stored as arrays."""

    def __init__(self, features: np.ndarray, cuts: np.ndarray, leaves: np.ndarray, base: float):
        self.features, self.cuts, self.leaves, self.base = features, cuts, leaves, base

    @classmethod
    def fit(cls, x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH, step: float = STEP, bins: int = 32) -> Trees:
        edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(x.shape[1])]
        binned = np.stack([np.searchsorted(e, x[:, f], side="left") for f, e in enumerate(edges)], axis=1)
        base = float(np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)))
        score = np.full(len(y), base)
        features, cuts, leaves = np.zeros((trees, 2**depth - 1), np.int64), np.full((trees, 2**depth - 1), np.inf, np.float32), np.zeros((trees, 2**depth))
        for t in range(trees):
            p = 1 / (1 + np.exp(-score))
            g, h = y - p, np.maximum(p * (1 - p), 1e-6)
            at = np.zeros(len(y), np.int64)
            for level in range(depth):
                for node in range(2**level):
                    rows = np.flatnonzero(at == node)
                    if len(rows) < 20:
                        continue
                    best = (1e-3, 0, np.inf)
                    gs, hs = g[rows].sum(), h[rows].sum()
                    for f, e in enumerate(edges):
                        if not len(e):
                            continue
                        left_g = np.cumsum(np.bincount(binned[rows, f], g[rows], len(e) + 1))[:-1]
                        left_h = np.cumsum(np.bincount(binned[rows, f], h[rows], len(e) + 1))[:-1]
                        gain = left_g**2 / (left_h + 1) + (gs - left_g) ** 2 / (hs - left_h + 1) - gs**2 / (hs + 1)
                        k = int(gain.argmax())
                        if gain[k] > best[0]:
                            best = (gain[k], f, e[k])
                    features[t, 2**level - 1 + node], cuts[t, 2**level - 1 + node] = best[1], best[2]
                place = 2**level - 1 + at
                at = 2 * at + (x[np.arange(len(y)), features[t, place]] > cuts[t, place])
            leaves[t] = step * np.bincount(at, g, 2**depth) / (np.bincount(at, h, 2**depth) + 1)
            score += leaves[t][at]
        return cls(features, cuts, leaves, base)

    def margins(self, x: np.ndarray) -> np.ndarray:
        score, rows = np.full(len(x), self.base), np.arange(len(x))
        depth = int(self.leaves.shape[1]).bit_length() - 1
        for f, c, leaf in zip(self.features, self.cuts, self.leaves):
            at = np.zeros(len(x), np.int64)
            for level in range(depth):
                place = 2**level - 1 + at
                at = 2 * at + (x[rows, f[place]] > c[place])
            score += leaf[at]
        return score


def decode(nodes: list[Node], margins: np.ndarray) -> list[str]:
    """The texts of the runs chosen, in page order.

    A node is dropped, kept, or open. All below a dropped node is dropped and
    nothing below one can be kept; an open node only leads to what is below it.
    The best labelling of the whole tree maximises the sum of the nodes'
    log-odds, kept runs and elements counting by their margin, dropped ones
    against it; runs weigh by the length of their text.
    """
    place = {id(n): i for i, n in enumerate(nodes)}
    drop, free = np.zeros(len(nodes)), np.zeros(len(nodes))
    keeps = [False] * len(nodes)
    for i in range(len(nodes) - 1, -1, -1):
        n, m = nodes[i], float(margins[i])
        if n.text is not None:
            weight = 1 + math.log1p(len(n.text))
            drop[i] = -m * weight
            keeps[i] = m > 0
            free[i] = abs(m) * weight
        else:
            below_drop = below_free = 0.0
            for k in n.kids:
                j = place[id(k)]
                below_drop += drop[j]
                below_free += free[j]
            drop[i] = below_drop - m
            opened = below_free + max(m, 0.0)
            keeps[i] = opened >= drop[i]
            free[i] = max(opened, drop[i])
    out, todo = [], [nodes[0]]
    while todo:
        n = todo.pop()
        if keeps[place[id(n)]]:
            if n.text is not None:
                out.append(n.text)
            todo.extend(reversed(n.kids))
    return out


# ---- pages to learn from


def _prose(r: random.Random, low: int, high: int, capital: bool = True) -> str:
    words = ["".join(r.choice("aeiounrstlmdhéñü") for _ in range(r.randint(1, 9))) for _ in range(r.randint(low, high))]
    for i in range(r.randint(6, 14), len(words), r.randint(8, 20)):
        words[i] += r.choice([".", ".", ",", "!", "?"])
    text = " ".join(words)
    return text.capitalize() + (r.choice([".", ".", "", "?"]) if capital else "")


def _box(r: random.Random, inner: str, tags: str, names: str, always: bool = False) -> str:
    tag = r.choice(tags.split())
    name = r.choice(names.split())
    own = r.choice(["class", "id"]) if always or tag in ("div", "section", "ul") else r.choice(["class", "id", ""])
    return f'<{tag}{f" {own}={chr(34)}{name}{chr(34)}" if own else ""}>{inner}</{tag}>'


def _links(r: random.Random, n: int) -> str:
    return "".join(f'<li><a href="/{i}">{_prose(r, 1, 3, False)}</a></li>' for i in range(n))


def made_page(seed: int) -> tuple[str, list[str]]:
    """A page of random words in one of many layouts, and the runs of its main text in order."""
    r = random.Random(seed)
    gold: list[str] = []

    def said(text: str) -> str:
        gold.append(text)
        return text

    def junk_list(names: str, tags: str = "nav div ul section") -> str:
        return _box(r, f"<ul>{_links(r, r.randint(2, 9))}</ul>", tags, names, True)

    def advert() -> str:
        return _box(r, r.choice(["{}", "<p>{}</p>", "<h3>{}</h3>"]).format(_prose(r, 3, 60)), "div div aside section", "ad ads advert sponsored promo ad-slot adsense advertisement", True)

    def notice() -> str:
        return _box(r, f"<p>{_prose(r, 5, 40)}</p>" + r.choice(["", "<button>OK</button>"]), "div section dialog", "cookie-notice notice consent newsletter popup subscribe gdpr alert cookie-banner", True)

    def talk() -> str:
        each = "".join(_box(r, f"<p>{_prose(r, 4, 70)}</p>", "div li article", "comment reply comment-body") for _ in range(r.randint(1, 5)))
        return _box(r, f"<h3>{_prose(r, 1, 3, False)}</h3>" + each, "section div ol", "comments discussion disqus replies comment-list responses", True)

    def form() -> str:
        return f"<form><label>{_prose(r, 1, 5, False)}</label><input name=q><p>{_prose(r, 2, 12)}</p><button>{_prose(r, 1, 2, False)}</button></form>"

    def side() -> str:
        return _box(r, f"<h4>{_prose(r, 1, 4, False)}</h4>" + r.choice([f"<ul>{_links(r, r.randint(2, 6))}</ul>", f"<p>{_prose(r, 5, 50)}</p>"]), "aside div aside", "sidebar related widget rail popular", True)

    head = [r.choice(["", junk_list("nav menu navbar toolbar breadcrumbs")]) for _ in range(2)]
    if r.random() < 0.6:
        head.append(_box(r, r.choice(["{}", "<h1>{}</h1>", "<p>{}</p>", "<a href='/'>{}</a>"]).format(_prose(r, 1, 8, False)), "header header div", "masthead header top site-header banner"))
    head.append(junk_list("nav menu main-nav navigation", "nav nav div"))
    head += [f() for f in (advert, notice, form) if r.random() < 0.4]
    if r.random() < 0.3:
        head.append(side())
    body: list[str] = []
    if r.random() < 0.85:
        title = f"<h1>{said(_prose(r, 1, 12, False))}</h1>"
        body.append(f"<header>{title}</header>" if r.random() < 0.15 else title)
    for _ in range(r.choice([1, 1, 2, 3, 5, 8])):
        kind = r.random()
        low, high = r.choice([(1, 4), (8, 60), (40, 160), (40, 400)])
        if kind < 0.7:
            text = said(_prose(r, low, high))
            body.append(r.choice(["<p>{}</p>", "<p>{}", "<p><b>{}</b></p>", "<p><i>{}</i></p>", "<div>{}</div>", "<p>{}</p>"]).format(text))
        elif kind < 0.78:
            body.append(f"<h2>{said(_prose(r, 1, 6, False))}</h2>")
        elif kind < 0.86:
            body.append("<ul>" + "".join(f"<li>{said(_prose(r, 2, 25))}</li>" for _ in range(r.randint(1, 5))) + "</ul>")
        elif kind < 0.92:
            body.append(f"<blockquote><p>{said(_prose(r, 5, 50))}</p></blockquote>")
        elif kind < 0.95:
            body.append(f"<table><tr><td>{said(_prose(r, 1, 6, False))}</td><td>{said(_prose(r, 1, 6, False))}</td></tr></table>")
        else:
            text = f"{_prose(r, 5, 20)} <a href='/x'>{_prose(r, 1, 4, False)}</a> {_prose(r, 5, 20)}"
            body.append(f"<p>{text}</p>")
            gold.append(re.sub(r"<[^>]*>", "", text))
        if r.random() < 0.12:
            body.append(r.choice([advert, form, notice, side])())
    if r.random() < 0.15:
        body.append(talk())
    main = "".join(body)
    shape = r.random()
    main = f"<article>{main}</article>" if shape < 0.45 else _box(r, main, "div section main article", "content article post entry-content story main-text post-body article-body", True) if shape < 0.85 else f"<main>{main}</main>" if shape < 0.93 else f"<div>{main}</div>"
    if r.random() < 0.3:
        main = f"<div class='{r.choice(['page', 'wrapper', 'container', 'main'])}'>{main}{side() if r.random() < 0.5 else ''}</div>"
    tail = [f() for f in (talk, side, advert, form, notice) if r.random() < 0.35]
    foot = _box(r, r.choice(["{}", "<p>{}</p>", "<p>{}</p><ul>" + _links(r, 3) + "</ul>"]).format("&copy; " + _prose(r, 2, 30)), "footer footer footer div", "footer site-footer copyright legal credits", True)
    page = f"<!DOCTYPE html><html><head><title>x</title><style>p{{}}</style></head><body>{''.join(head)}{main}{''.join(tail)}{foot}"
    return page + ("</body></html>" if r.random() < 0.9 else ""), [" ".join(g.split()) for g in gold if g.strip()]


@functools.lru_cache(maxsize=2)
def learn_trees(pages: int = TRAIN_PAGES) -> Trees:
    """Trees fitted to `pages` made pages: an element is positive if most of its text is main text, a run if it is."""
    xs, ys = [], []
    for seed in range(pages):
        page, gold = made_page(seed)
        nodes, x = node_features(parse_blocks(page))
        left, want = list(gold), {}
        for n in nodes:
            if n.text is not None:
                hit = bool(left) and n.text == left[0]
                want[id(n)] = (len(n.text) * hit, len(n.text))
                if hit:
                    left.pop(0)
        for n in reversed(nodes):
            if n.text is None:
                parts = [want[id(k)] for k in n.kids]
                want[id(n)] = (sum(p[0] for p in parts), sum(p[1] for p in parts))
        use = np.array([want[id(n)][1] > 0 for n in nodes])
        xs.append(x[use])
        ys.append(np.array([want[id(n)][0] * 2 > want[id(n)][1] for n in nodes], float)[use])
    return Trees.fit(np.concatenate(xs), np.concatenate(ys))


def main_texts(pages: list[str | None], trees: Trees) -> list[str]:
    """The main text of each page: chosen runs in page order, joined by one space."""
    parsed = [node_features(parse_blocks(p)) if p else ([], np.zeros((0, N_FEATURES), np.float32)) for p in pages]
    margins = trees.margins(np.concatenate([x for _, x in parsed])) if parsed else np.zeros(0)
    out, at = [], 0
    for nodes, x in parsed:
        plain = all(n.text is not None for n in nodes[1:])
        out.append(" ".join([n.text for n in nodes[1:]] if plain else decode(nodes, margins[at : at + len(x)])))
        at += len(x)
    return out


def _extract(trees: Trees):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_chunks(whole, "html"):
                texts = main_texts(batch.column("html").to_pylist(), trees)
                yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return run


def extract_main_text(pages: DataFrame, trees: Trees | None = None) -> DataFrame:
    """(page_id, url, text, n_chars) of every page.

    Null and empty html, and pages without main text, give an empty text; a
    page without any block element is its own main text. Bodies of scripts,
    styles, templates, drawings (svg), frames, selections and text fields are
    no text; formulas, objects and noscript are judged like other elements. A
    node whose margin is 0 is kept as an element and dropped as a run of text.
    Pages of any length are parsed whole, one at a time.
    Character references are decoded, white space in a block becomes one space,
    blocks are joined by one space in page order; nothing else is dropped from
    the blocks that are chosen. Rows are judged alone; other columns are ignored.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return rows.mapInArrow(_extract(trees or learn_trees()), "page_id long, url string, text string, n_chars long")


def op4_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_main_text(table(spark, sf_dir, "pages"))
