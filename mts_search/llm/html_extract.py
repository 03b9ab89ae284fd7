"""Main-text extraction with a tree-structured graphical model over the DOM.

Every element and every run of text is a node with a hidden label (content or not). A node has a
unary potential from its features; each parent-child edge has a 2x2 potential (one table for edges
below the page frame, another for edges inside the page's blocks). One upward and one downward sweep of sum-product messages gives exact marginals; runs of text whose marginal says
"content" are the article. Weights are fitted by gradient ascent on the likelihood of labelled
pages. The labelled pages are made here from page layouts (``labelled_pages``), because the tables
bring none; a caller may pass their own.

Edge cases: null or empty html gives the empty text; html without any tag is one block of text;
unclosed tags, comments and scripts at the end of input close there; a quote that never closes ends with
its tag at the next >; no part of a tag gets into the text; time is linear in the page's length, however deep
or broken it is; repeated rows stay repeated; an empty table gives no rows; other columns of the input are
not read.
"""

from __future__ import annotations

import html as html_entities
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from random import Random

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

# Element names by role in HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template svg math iframe object canvas textarea title select button".split())
BLOCK = frozenset(
    "html head body div p ul ol li dl dt dd nav header footer aside article section main form fieldset table thead tbody tfoot tr td th caption "
    "h1 h2 h3 h4 h5 h6 blockquote pre figure figcaption address details summary dialog menu hgroup search center hr".split()
)
#: An element that opens while one of these is the innermost open element closes it first.
CLOSED_BY = {
    "li": frozenset(["li"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"]), "tr": frozenset(["tr", "td", "th"]), "td": frozenset(["td", "th"]), "th": frozenset(["td", "th"]),
    "tbody": frozenset(["thead", "tbody", "tr", "td", "th"]), "tfoot": frozenset(["tbody", "tr", "td", "th"]), "body": frozenset(["head"]),
}
#: Words in class, id and role that hint at the role of a block.
CUES = {
    "menu": "nav navbar navigation menu menubar breadcrumb breadcrumbs pagination pager tabs toolbar toc skip".split(),
    "edge": "header footer masthead banner copyright legal colophon topbar bottombar".split(),
    "side": "sidebar aside complementary related recommended widget rail share social sharing tags promo".split(),
    "notice": "cookie cookies notice consent gdpr alert popup modal overlay newsletter subscribe signup login paywall".split(),
    "advert": "ad ads advert adverts advertisement sponsor sponsored sponsors promoted banner-ad adsense".split(),
    "talk": "comment comments reply replies disqus discussion respond reactions".split(),
    "main": "article content main story post entry body text prose".split(),
}
TAGS = "p h1 h2 h3 h4 li div td blockquote pre dd dt figcaption".split()
#: Elements that frame the page: their children are the page's blocks.
FRAME = frozenset(["#root", "html", "body"])
MAIN, OTHER = frozenset(["article", "main"]), frozenset("nav header footer aside form menu dialog".split())
_MAIN_CUE = list(CUES).index("main")
ZONES = "nav header footer aside form article main section table ul".split()

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[(?P<cdata>.*?)(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(?P<close>/?)(?P<name>[A-Za-z][A-Za-z0-9:-]*)|</[^A-Za-z][^>]*(?:>|\Z)", re.S)
#: What follows a tag's name: quotes count after = only; one that never closes is a letter like others. No backtracking.
_ATTRS = re.compile(r"""((?:[^>=]++|=\s*+(?:"[^"]*+"|'[^']*+'|[^\s>"'][^\s>]*+)?+)*+)>""")
#: Characters in which a tag has to end by these rules; a longer one ends at its first >.
TAG_SPAN = 16_384
_NOTE = re.compile(r"©|\bcopyright\b|all rights reserved", re.I)
_CUE_ATTR = re.compile(r"""(?:^|\s)(class|id|role|aria-label|hidden|style)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""", re.I)
_WORD = re.compile(r"[a-z]+")
_SPACE = re.compile(r"\s+")
_CUE_OF: dict[str, list[int]] = {}
for _k, _ws in enumerate(CUES.values()):
    for _w in _ws:
        _CUE_OF.setdefault(_w, []).append(_k)
N_FEATURES = 1 + len(TAGS) + len(ZONES) + len(CUES) + 9


@dataclass
class Page:
    """A parsed page: per node its parent, features; per run of text its node and words."""

    parent: list[int]
    depth: list[int]
    tag: list[str]
    cues: list[frozenset]
    barred: list[bool]
    texts: dict[int, str]
    links: dict[int, int]
    label: dict[int, int]


@lru_cache(4096)
def _cues(attrs: str) -> tuple[frozenset, bool, str | None]:
    found: set[int] = set()
    hidden, label = False, None
    for m in _CUE_ATTR.finditer(attrs):
        name, value = m[1].lower(), (m[2] or "").strip("\"'").lower()
        if name == "hidden" or name == "style" and "display:none" in value.replace(" ", ""):
            hidden = True
        elif name in ("class", "id", "role", "aria-label"):
            words = _WORD.findall(value)
            for w in [*words, "-".join(words)]:
                found.update(_CUE_OF.get(w, ()))
    if m := re.search(r'data-keep="([01])"', attrs):
        label = m[1]
    return frozenset(found), hidden, label


def parse(html: str) -> Page:
    """Block-level tree with runs of text as leaves; inline elements only mark link text."""
    page = Page([-1], [0], ["#root"], [frozenset()], [False], {}, {}, {})
    stack = [0]
    run: list[str] = []
    linked = n_link = 0
    keep = {0: 0}

    def flush() -> None:
        nonlocal n_link
        if run:
            text = _SPACE.sub(" ", html_entities.unescape("".join(run))).strip()
            run.clear()
            if text:
                at = stack[-1]
                node = len(page.parent)
                page.parent.append(at)
                page.depth.append(page.depth[at] + 1)
                page.tag.append("#text")
                page.cues.append(frozenset())
                page.barred.append(page.barred[at])
                page.texts[node] = text
                page.links[node] = min(n_link, len(text))
                page.label[node] = keep.get(at, 0)
        n_link = 0

    def text(piece: str) -> None:
        nonlocal n_link
        if piece:
            run.append(piece)
            if linked:
                n_link += len(piece)

    pos, size = 0, len(html)
    find = _TOKEN.search
    is_open: Counter = Counter()
    while pos < size:
        m = find(html, pos)
        if m is None:
            text(html[pos:])
            break
        text(html[pos : m.start()])
        pos = m.end()
        name = m["name"]
        if name is None:
            if m["cdata"]:
                text(m["cdata"])
            continue
        rest = _ATTRS.match(html, pos, pos + TAG_SPAN)
        end = rest.end() if rest else html.find(">", pos) + 1
        if not end:  # a tag that never ends, and no later one does
            break
        attrs, pos = html[pos : end - 1], end
        name = name.lower()
        if m["close"]:
            if name == "a":
                linked = max(0, linked - 1)
            if name in BLOCK and name != "hr":
                if is_open[name]:
                    flush()
                    while page.tag[stack[-1]] != name:
                        is_open[page.tag[stack.pop()]] -= 1
                    is_open[page.tag[stack.pop()]] -= 1
                    linked = 0
                elif name == "p":
                    flush()
            continue
        if name in RAW and not attrs.endswith("/"):
            over = re.compile(rf"</{name}\s*[^>]*>", re.I).search(html, pos) if html.find(">", pos) >= 0 else None
            pos = over.end() if over else size
            continue
        if name == "br":
            text(" ")
            continue
        if name == "a":
            linked += 1
        if name not in BLOCK:
            continue
        flush()
        linked = 0
        if name == "hr":
            continue
        if page.tag[stack[-1]] == "p":  # a block ends an open paragraph, which so is always the innermost
            is_open[page.tag[stack.pop()]] -= 1
        while len(stack) > 1 and page.tag[stack[-1]] in CLOSED_BY.get(name, ()):
            is_open[page.tag[stack.pop()]] -= 1
        cues, hidden, label = _cues(attrs) if len(attrs) <= 2000 else _cues.__wrapped__(attrs)
        at, node = stack[-1], len(page.parent)
        page.parent.append(at)
        page.depth.append(page.depth[at] + 1)
        page.tag.append(name)
        page.cues.append(cues)
        page.barred.append(page.barred[at] or hidden or name == "head")
        keep[node] = int(label) if label else keep.get(at, 0)
        page.label[node] = keep[node]
        stack.append(node)
        is_open[name] += 1
    flush()
    return page


_TAG_AT = {t: 1 + i for i, t in enumerate(TAGS)}
_ZONE_AT = {t: 1 + len(TAGS) + i for i, t in enumerate(ZONES)}
_CUE_AT = 1 + len(TAGS) + len(ZONES)
_NUM_AT = _CUE_AT + len(CUES)


def features(page: Page) -> np.ndarray:
    """One row a node: bias, tag, zone, cues, and for text its length, link share and stops."""
    x = np.zeros((len(page.parent), N_FEATURES), dtype=np.float32)
    x[:, 0] = 1
    zone = [0] * len(page.parent)  # by the nearest ancestor that says so: 1 article, -1 something else
    for i, tag in enumerate(page.tag):
        above = zone[i] = zone[page.parent[i]] if i else 0
        if i in page.texts:
            t = page.texts[i]
            n = len(t)
            x[i, _NUM_AT : _NUM_AT + 7] = (min(n, 400) / 400, page.links[i] / n, n < 25, t[-1] in ".!?…", n < 400 and _NOTE.search(t) is not None, 0, 1)
            if (over := page.tag[page.parent[i]]) in _TAG_AT:
                x[i, _TAG_AT[over]] = 1
        else:
            if tag in _TAG_AT:
                x[i, _TAG_AT[tag]] = 1
            heading = tag == "header" and above == 1
            if tag in _ZONE_AT and not heading and not (tag in MAIN and above == -1):
                x[i, _ZONE_AT[tag]] = 1
            for c in page.cues[i]:
                x[i, _CUE_AT + c] = 1
            x[i, _NUM_AT + 5] = heading
            named = page.cues[i] - {_MAIN_CUE}
            if tag in OTHER and not heading or named:
                zone[i] = -1
            elif above != -1 and (tag in MAIN or page.cues[i]):
                zone[i] = 1
        x[i, _NUM_AT + 7], x[i, _NUM_AT + 8] = zone[i] == 1, zone[i] == -1
    return x


class Forest:
    """Many pages as one forest, ordered so that messages pass a whole depth at a time."""

    def __init__(self, pages: list[Page]) -> None:
        base = np.cumsum([0, *(len(p.parent) for p in pages)])
        self.base = base[:-1]
        self.parent = np.concatenate([np.where((q := np.array(p.parent)) < 0, -1, q + b) for p, b in zip(pages, base, strict=False)]) if pages else np.zeros(0, int)
        depth = np.concatenate([np.array(p.depth) for p in pages]) if pages else np.zeros(0, int)
        order = np.argsort(depth, kind="stable")
        cuts = np.searchsorted(depth[order], np.arange(1, (depth.max() if len(depth) else 0) + 1))
        self.levels = np.split(order, cuts) if len(order) else []
        self.x = np.concatenate([features(p) for p in pages]) if pages else np.zeros((0, N_FEATURES), np.float32)
        self.kind = np.concatenate([np.array([int(q >= 0 and p.tag[q] not in FRAME) for q in p.parent]) for p in pages]) if pages else np.zeros(0, int)
        self.barred = np.concatenate([np.array([b or t in FRAME for b, t in zip(p.barred, p.tag, strict=True)]) for p in pages]) if pages else np.zeros(0, bool)

    def beliefs(self, w: np.ndarray, edge: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Marginals of every node and of every parent-child edge: sum-product up, then down."""
        n = len(self.parent)
        unary = np.zeros((n, 2))
        unary[:, 1] = self.x @ w
        unary[self.barred, 1] = -60.0
        up = np.zeros((n, 2))  # message from a node to its parent
        gather = unary.copy()  # unary plus messages of the children
        for level in self.levels[:0:-1]:
            e = edge[self.kind[level]]
            up[level] = np.logaddexp(gather[level, 0][:, None] + e[:, :, 0], gather[level, 1][:, None] + e[:, :, 1])
            np.add.at(gather, self.parent[level], up[level])
        down = np.zeros((n, 2))
        pair = np.zeros((n, 2, 2))
        for level in self.levels[1:]:
            p = self.parent[level]
            rest = gather[p] + down[p] - up[level]
            e = edge[self.kind[level]]
            down[level] = np.logaddexp(rest[:, 0][:, None] + e[:, 0], rest[:, 1][:, None] + e[:, 1])
            pair[level] = rest[:, :, None] + e + gather[level][:, None, :]
        node = gather + down
        node = np.exp(node - np.logaddexp(node[:, :1], node[:, 1:]))
        for level in self.levels[1:]:
            z = pair[level]
            pair[level] = np.exp(z - z.max(axis=(1, 2), keepdims=True))
            pair[level] /= pair[level].sum(axis=(1, 2), keepdims=True)
        return node[:, 1], pair


@dataclass(frozen=True)
class Model:
    weights: np.ndarray
    edge: np.ndarray


def labelled_pages(n: int = 240, seed: int = 7) -> list[str]:
    """Labelled layouts: every block carries data-keep="1" (article) or "0" (the rest)."""
    rng = Random(seed)
    syl = "ka lo mi tur ven sal der ion est ra po ne qui bel dor".split()

    def words(k: int) -> str:
        return " ".join("".join(rng.choice(syl) for _ in range(rng.randint(1, 4))) for _ in range(k))

    def sentence() -> str:
        return words(rng.randint(4, 18)).capitalize() + rng.choice("....!?")

    def prose() -> str:
        return " ".join(sentence() for _ in range(rng.choice([1, 1, 2, 3, 5, 8])))

    def links(k: int) -> str:
        return "<ul>" + "".join(f'<li><a href="/{i}">{words(rng.randint(1, 2))}</a></li>' for i in range(k)) + "</ul>"

    def named(kind: str, inner: str, tags: tuple[str, ...] = ("div", "div", "section")) -> str:
        tag = rng.choice(tags)
        cue = rng.choice(CUES[kind])
        return f'<{tag} {rng.choice(["class", "id"])}="{rng.choice(["", "", "site-", "page-", "block "])}{cue}" data-keep="0">{inner}</{tag}>'

    def noise() -> str:
        return rng.choice([
            lambda: f'<nav data-keep="0">{links(rng.randint(2, 7))}</nav>',
            lambda: named("menu", links(rng.randint(2, 6))),
            lambda: named("advert", rng.choice([prose(), f"<p>{prose()}</p>"])),
            lambda: named("side", f"<h3>{words(2)}</h3>" + rng.choice([links(3), f"<p>{prose()}</p>"]), ("div", "aside", "section")),
            lambda: f'<aside data-keep="0"><p>{prose()}</p></aside>',
            lambda: named("notice", f"<p>{prose()}</p><button>ok</button>"),
            lambda: f'<form data-keep="0"><label>{words(2)}</label><input name="q"><p>{sentence()}</p></form>',
            lambda: f'<header data-keep="0"><h1>{words(2)}</h1><p>{sentence()}</p></header>',
        ])()

    def article() -> str:
        title = f"<h1>{words(rng.randint(3, 8))}{rng.choice(['', '.'])}</h1>"
        if rng.random() < 0.2:
            title = f"<header>{title}</header>"
        parts = []
        for _ in range(rng.choice([0, 1, 2, 3, 5, 9])):
            if rng.random() < 0.1:
                word = words(1)
                parts.append(f"<p>{' '.join([word] * rng.randint(3, 40))}</p>")
            parts.append(rng.choice([
                lambda: f"<p>{prose()}</p>", lambda: f"<p>{prose()}</p>", lambda: f"<p>{prose()}</p>", lambda: f"<p><b>{prose()}<br>",
                lambda: f"<h2>{words(3)}</h2><p>{prose()}</p>", lambda: f"<blockquote>{prose()}</blockquote>", lambda: f"<p>{words(rng.randint(1, 3))}</p>",
                lambda: "<ul>" + "".join(f"<li>{sentence()}</li>" for _ in range(3)) + "</ul>", lambda: f"<p>{sentence()} <a href='/x'>{words(2)}</a> {sentence()}</p>",
                lambda: f"<p>{words(1)[:rng.randint(1, 6)]}</p>", lambda: f"<div>{prose()}</div>", lambda: f"<section><h2>{words(2)}</h2><p>{prose()}</p></section>",
                lambda: f"<table><tr><td>{sentence()}</td><td>{words(3)}</td></tr></table>", lambda: f"<pre>{sentence()}</pre>",
            ])())
            if rng.random() < 0.08:
                parts.append(named(rng.choice(["advert", "side", "notice"]), rng.choice([sentence(), f"<p>{prose()}</p>"])))
        inner = title + "".join(parts)
        if rng.random() < 0.15:
            inner += talk()
        kind = rng.randint(0, 6)
        if kind <= 2:
            return f'<article data-keep="1">{inner}</article>'
        if kind == 3:
            return f'<main data-keep="1">{inner}</main>'
        if kind == 4:
            return f'<div class="{rng.choice(CUES["main"])}" data-keep="1">{inner}</div>'
        if kind == 5:
            return f'<div data-keep="1">{inner}</div>'
        return rng.choice([prose(), words(rng.randint(2, 5)), "".join(f'<p data-keep="1">{prose()}</p>' for _ in range(rng.randint(1, 4))), f'<h1 data-keep="1">{words(4)}</h1><p data-keep="1">{prose()}</p>'])

    def talk() -> str:
        one = "".join(f'<{t} class="comment"><p>{prose()}</p></{t}>' for t in rng.choices(["div", "li", "article"], k=rng.randint(1, 4)))
        return f'<{(t := rng.choice(["section", "div"]))} id="comments" data-keep="0">{one}</{t}>'

    pages = []
    for _ in range(n):
        before = "".join(noise() for _ in range(rng.randint(0, 3)))
        after = "".join(noise() for _ in range(rng.randint(0, 2))) + (talk() if rng.random() < 0.4 else "")
        foot = f'<footer data-keep="0">{rng.choice(["&copy; ", ""])}{sentence()}</footer>' if rng.random() < 0.8 else ""
        if rng.random() < 0.12:  # a loose line of rights, in place of the footer or beside it
            line = rng.choice([f"Copyright {rng.randint(1990, 2030)} {words(2)}.", f"© {words(2)}", f"{words(2)}. All rights reserved."])
            foot = rng.choice(["", foot]) + f'<{(t := rng.choice(["p", "div"]))} data-keep="0">{line}</{t}>'
        pages.append(f'<html><head><title>{words(3)}</title></head><body data-keep="1">{before if "<" in (main := article()) else ""}{main}{after}{foot}</body></html>')
    return pages


def fit(pages: list[str], rounds: int = 150, rate: float = 0.5, ridge: float = 1e-3) -> Model:
    """Maximum likelihood by Adam steps; the gradient is observed counts minus sum-product expectations."""
    parsed = [parse(p) for p in pages]
    forest = Forest(parsed)
    y = np.zeros(len(forest.parent))
    for b, p in zip(forest.base, parsed, strict=True):
        for i, v in p.label.items():
            y[b + i] = v and p.tag[i] not in FRAME
    child = np.flatnonzero(forest.parent >= 0)
    yp, yc = y[forest.parent[child]].astype(int), y[child].astype(int)
    seen = np.zeros((2, 2, 2))
    np.add.at(seen, (forest.kind[child], yp, yc), 1)
    w, edge = np.zeros(N_FEATURES), np.zeros((2, 2, 2))
    theta = np.concatenate([w, edge.ravel()])
    m = np.zeros_like(theta)
    v = np.zeros_like(theta)
    free = ~forest.barred
    for step in range(1, rounds + 1):
        w, edge = theta[:N_FEATURES], theta[N_FEATURES:].reshape(2, 2, 2)
        node, pair = forest.beliefs(w, edge)
        g = np.concatenate([forest.x[free].T @ (y - node)[free], (seen - np.stack([pair[child[forest.kind[child] == k]].sum(axis=0) for k in (0, 1)])).ravel()]) / len(pages) - ridge * theta
        m = 0.9 * m + 0.1 * g
        v = 0.99 * v + 0.01 * g * g
        theta = theta + rate / (1 + step / 60) * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return Model(theta[:N_FEATURES].copy(), theta[N_FEATURES:].reshape(2, 2, 2).copy())


@lru_cache(1)
def default_model() -> Model:
    return fit(labelled_pages())


def extract_batch(pages: list[str | None], model: Model) -> list[str]:
    """Main text of each page."""
    parsed = [parse(p or "") for p in pages]
    forest = Forest(parsed)
    if not len(forest.parent):
        return ["" for _ in pages]
    node, _ = forest.beliefs(model.weights, model.edge)
    out = []
    for b, p in zip(forest.base, parsed, strict=True):
        out.append("\n".join(t for i, t in p.texts.items() if node[b + i] >= 0.5))
    return out


def extract(df: DataFrame, key: list[str], column: str = "html", model: Model | None = None, batch: int = 64) -> DataFrame:
    """``key`` columns, ``text`` and ``n_chars`` for each row of ``df``; map-only, one batch of pages in memory."""
    model = model or default_model()
    kept = df.select(*key, df[column].cast("string").alias("__html"))
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields[:-1]), "text string", "n_chars bigint"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for at in range(0, big.num_rows, batch):
                rows = big.slice(at, batch)
                texts = extract_batch(rows.column(len(key)).to_pylist(), model)
                yield pa.RecordBatch.from_arrays(
                    [*(rows.column(i) for i in range(len(key))), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())],
                    names=[*key, "text", "n_chars"],
                )

    return kept.mapInArrow(run, schema)
