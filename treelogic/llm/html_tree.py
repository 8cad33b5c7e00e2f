"""Main text of web pages by a tree-structured graphical model over the DOM.

Every block element is a binary variable, content or not.  Its own evidence (tag,
words in class, id and role, amount of text, share of links) gives it a
potential, and each parent and child share one more, so that a paragraph is
judged with the section it stands in.  The graph is a tree, so two sweeps of
sum-product messages, up and down, give every element's exact marginal; text of
elements that are content with probability over one half is kept.

The weights are those of most likelihood on labelled pages (``labelled_pages``
builds them from page plans with known article text); the gradient is the
difference of observed and expected feature counts, which the same two sweeps
give.  Sweeps run level by level over all pages of a batch at once.
"""

from __future__ import annotations

import random
import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache
from html import unescape

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.llm import arrowkit

# HTML's block-level elements, raw-text elements and void elements that matter here.
_BLOCK = set("html body article main section div p h1 h2 h3 h4 h5 h6 ul ol li dl dt dd nav header footer aside form fieldset table thead tbody tfoot tr td th caption blockquote pre figure figcaption address details summary dialog hr button select option label legend center iframe noscript hgroup menu search".split())
_RAW = {"script", "style", "title", "textarea", "template", "xmp", "svg", "math", "object"}
_VOID = {"hr", "iframe"}
_CLOSES_P = _BLOCK - {"button", "label", "option", "select"}
_P_SCOPE = {"button", "td", "th", "caption", "article", "section", "div", "body"}
_SIBLINGS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
_SCOPE = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table", "tr"}, "th": {"table", "tr"}, "option": {"select"}}
_TAGS = ["article", "main", "section", "div", "p", "h1", "h2", "list", "li", "nav", "header", "footer", "aside", "form", "table", "cell", "quote", "figure", "control", "address", "details", "page", "hidden", "other"]
_TAG_GROUP = {"h3": "h2", "h4": "h2", "h5": "h2", "h6": "h2", "ul": "list", "ol": "list", "dl": "list", "menu": "list", "dt": "li", "dd": "li", "fieldset": "form", "thead": "table", "tbody": "table", "tfoot": "table", "tr": "table", "td": "cell", "th": "cell", "caption": "cell", "blockquote": "quote", "pre": "quote", "figcaption": "figure", "button": "control", "select": "control", "option": "control", "label": "control", "legend": "control", "dialog": "hidden", "noscript": "hidden", "summary": "details", "html": "page", "body": "page", "center": "div", "iframe": "control", "hr": "other", "search": "form", "hgroup": "header"}
_HINTS = {
    "menu": r"nav|menu|crumb|pager|pagination|toc|tabs|skip|toolbar",
    "ad": r"ads?|advert\w*|sponsor\w*|promo\w*|banner|adsense|adbox|adslot|outbrain|taboola",
    "side": r"side|sidebar|aside|widget|related|recommend\w*|rail|trending|popular|more",
    "foot": r"foot|footer|bottom|copyright|legal|colophon",
    "head": r"head|header|masthead|topbar|logo|site|brand",
    "notice": r"cookie\w*|consent|notice|alert|popup|modal|newsletter|subscribe|signup|toast|gdpr|paywall|overlay|privacy|warning|message",
    "comment": r"comments?|reply|replies|disqus|discussion|respond|responses?|reviews?|feedback|thread|reader",
    "share": r"share|sharing|social|follow|tags?|meta|byline|author|rating|tools?",
    "form": r"form|search|login|input|field|contact|button|btn",
    "hidden": r"hidden|hide|invisible|sr|print",
    "content": r"article|content|post|entry|story|main|body|text|prose|page|blog|news",
}
_HINT = {name: re.compile(rf"(?:^|[^a-z])(?:{p})(?![a-z])") for name, p in _HINTS.items()}
_LENGTHS = (1, 25, 80, 200)
_SHARES = (0.01, 0.3, 0.7)
_FEATURES = [f"tag {t}" for t in _TAGS] + [f"hint {h}" for h in _HINTS] + [f"own {i}" for i in range(5)] + [f"links {i}" for i in range(4)] + [f"below {i}" for i in range(5)] + ["stop", "bias", "hidden style", "role"]
_ID = {name: i for i, name in enumerate(_FEATURES)}

# A tag's attributes as in the HTML standard: a value that does not begin with a quote ends at white space or ``>``, and
# quotes inside it are plain characters.  All repetitions are possessive, so a tag is read once whatever it holds.
_ATTRIBUTES = r"""(?:[\s/]++|[^\s/>=]++(?:\s*+=\s*+(?:"[^"]*+"|'[^']*+'|[^\s"'>][^\s>]*+)?+)?+|=[^\s/>=]*+)*+"""
_MARK = re.compile(rf"<(?:!--.*?(?:-->|\Z)|(/?)([a-zA-Z][^\s/>]*+)({_ATTRIBUTES})>|[!?/][^>]*+(?:>|\Z))", re.S)
#: For pages that end inside a tag: here no tag reaches over the next ``<``.
_SHORT_MARK = re.compile(r"<(?:!--.*?(?:-->|\Z)|(/?)([a-zA-Z][^\s/<>]*+)([^<>]*+)>|[!?/][^<>]*+(?:>|\Z|(?=<)))", re.S)
_HEAD_END = re.compile(r"</head\b[^<>]*+>|<body\b", re.I)
_ATTRIBUTE = re.compile(r"""(?:^|\s)(class|id|role|style|aria-hidden|hidden|aria-label)\s*(?:=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""", re.I)


@lru_cache(maxsize=20_000)
def _attribute_features(text: str) -> tuple[int, ...]:
    words, out = [], set()
    for m in _ATTRIBUTE.finditer(text):
        name, value = m[1].lower(), (m[2] or m[3] or m[4] or "")
        if name in ("class", "id", "role", "aria-label"):
            # camelCase and separators give words
            words.append(re.sub(r"([a-z0-9])([A-Z])", r"\1 \2", value).lower())
            if name == "role" and value.lower() in ("navigation", "banner", "complementary", "contentinfo", "search", "dialog", "alert", "alertdialog", "menu"):
                out.add(_ID["role"])
        elif name == "hidden" or name == "aria-hidden" and value.lower() == "true" or name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I):
            out.add(_ID["hidden style"])
    text = " ".join(words)
    return tuple(sorted(out | {_ID[f"hint {h}"] for h, p in _HINT.items() if p.search(text)})) if text or out else ()


@lru_cache(maxsize=1000)
def _raw_end(tag: str) -> re.Pattern:
    return re.compile(rf"</{re.escape(tag)}(?=[\s/>])[^<>]*+>", re.I)


@dataclass
class Page:
    """Block elements with parents before children, and blocks of text in page order."""

    parent: list[int] = field(default_factory=lambda: [-1])
    depth: list[int] = field(default_factory=lambda: [0])
    kind: list[str] = field(default_factory=lambda: ["page"])
    hints: list[tuple[int, ...]] = field(default_factory=lambda: [()])
    own: list[int] = field(default_factory=lambda: [0])
    links: list[int] = field(default_factory=lambda: [0])
    stops: list[bool] = field(default_factory=lambda: [False])
    blocks: list[tuple[int, str]] = field(default_factory=list)


def parse(html: str) -> Page:
    """The page's block tree; never fails, whatever the markup."""
    page = Page()
    stack: list[tuple[str, int]] = [("", 0)]
    opened: dict[str, int] = {}  # how many elements of a tag are on the stack, so as not to look for what is not there
    buffer: list[str] = []
    linked = in_link = 0
    at, n = 0, len(html)
    headless = False
    mark = _MARK

    def flush() -> None:
        nonlocal linked
        text = " ".join("".join(buffer).split())
        buffer.clear()
        if text:
            node = stack[-1][1]
            page.blocks.append((node, text))
            page.own[node] += len(text)
            page.links[node] += min(linked, len(text))
            page.stops[node] = page.stops[node] or text[-1] in ".!?…"
        linked = 0

    def leave(i: int) -> None:
        """Closes the elements from place i of the stack on."""
        for tag, _ in stack[i:]:
            opened[tag] -= 1
        del stack[i:]

    def add(text: str) -> None:
        """A text node; its references are its own, whatever stands beside it."""
        nonlocal linked
        if "&" in text:
            text = unescape(text)
        buffer.append(text)
        if in_link:
            linked += len(text)

    def next_mark(at: int):
        """The text up to the next tag or comment, and that."""
        nonlocal mark
        start = at
        while True:
            at = html.find("<", at)
            if at < 0 or at + 1 >= n:
                return html[start:], None
            after = html[at + 1]
            if not (after.isascii() and after.isalpha() or after in "!?/"):
                at += 1
                continue
            found = mark.match(html, at)
            if found:
                return html[start:at], found
            if mark is _MARK and (after != "/" or html[at + 2:at + 3].isalpha()):
                mark = _SHORT_MARK  # the page ends inside this tag: from here on tags are short
            else:
                at += 1

    while at < n:
        text, m = next_mark(at)
        if text:
            add(text)
        if m is None:
            break
        at = m.end()
        tag = m[2]
        if tag is None:
            continue
        tag = tag.lower()
        if m[1]:
            if tag == "a":
                in_link = 0
            elif tag in _BLOCK:
                flush()
                if opened.get(tag):
                    i = len(stack) - 1
                    while stack[i][0] != tag:
                        i -= 1
                    leave(i)
            continue
        if tag in _RAW:
            if not m[3].endswith("/"):
                end = _raw_end(tag).search(html, at)
                at = end.end() if end else n
            continue
        if tag == "head":
            end = None if headless else _HEAD_END.search(html, at)
            headless = True
            if end:
                at = end.start() if html[end.start() + 1] != "/" else end.end()
            continue
        if tag == "br":
            buffer.append(" ")
        elif tag == "a":
            in_link = 1
        elif tag in _BLOCK:
            flush()
            in_link = 0 if tag in ("p", "li", "nav", "article") else in_link
            if tag in _CLOSES_P and opened.get("p"):
                for i in range(len(stack) - 1, 0, -1):
                    if stack[i][0] == "p":
                        leave(i)
                        break
                    if stack[i][0] in _P_SCOPE:
                        break
            if tag in _SIBLINGS and any(opened.get(t) for t in _SIBLINGS[tag]):
                for i in range(len(stack) - 1, 0, -1):
                    if stack[i][0] in _SCOPE[tag]:
                        break
                    if stack[i][0] in _SIBLINGS[tag]:
                        leave(i)
                        break
            node = len(page.parent)
            page.parent.append(stack[-1][1])
            page.depth.append(len(stack))
            page.kind.append(_TAG_GROUP.get(tag, tag))
            page.hints.append(_attribute_features(m[3]) if m[3] else ())
            page.own.append(0)
            page.links.append(0)
            page.stops.append(False)
            if tag not in _VOID and not m[3].endswith("/") or tag == "p":
                stack.append((tag, node))
                opened[tag] = opened.get(tag, 0) + 1
    flush()
    return page


def features(page: Page) -> tuple[list[int], list[int]]:
    """Feature numbers of all elements one after the other, and how many each has."""
    below, linked = page.own[:], page.links[:]
    for v in range(len(below) - 1, 0, -1):
        below[page.parent[v]] += below[v]
        linked[page.parent[v]] += linked[v]
    flat, count = [], []
    own0, links0, below0, stop, bias = _ID["own 0"], _ID["links 0"], _ID["below 0"], _ID["stop"], _ID["bias"]
    for kind, hints, own, size, link, ends in zip(page.kind, page.hints, page.own, below, linked, page.stops):
        share = link / size if size else 0.0
        row = [_ID["tag " + kind], bias, own0 + (own >= 1) + (own >= 25) + (own >= 80) + (own >= 200), links0 + (share > 0.01) + (share > 0.3) + (share > 0.7), below0 + (size >= 1) + (size >= 25) + (size >= 80) + (size >= 200), *hints]
        if ends:
            row.append(stop)
        flat += row
        count.append(len(row))
    return flat, count


class Forest:
    """The elements of many pages as one forest, by levels."""

    def __init__(self, pages: list[Page]):
        flat: list[int] = []
        count: list[int] = []
        parent, depth, first = [], [], [0]
        for page in pages:
            f, c = features(page)
            flat += f
            count += c
            base = first[-1]
            parent += [p + base if p >= 0 else -1 for p in page.parent]
            depth += page.depth
            first.append(base + len(page.parent))
        self.first = first
        self.flat, self.count = np.array(flat, np.int64), np.array(count, np.int64)
        self.owner = np.repeat(np.arange(len(count)), self.count)
        self.parent = np.array(parent, np.int64)
        d = np.array(depth, np.int64)
        by_depth = np.argsort(d, kind="stable")
        self.levels = np.split(by_depth, np.cumsum(np.bincount(d))[:-1]) if len(d) else []

    def marginals(self, weights: np.ndarray, edge: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """P(content) of every element and the joint table with its parent (elements x 2 x 2)."""
        n = len(self.count)
        up = np.zeros((n, 2))
        up[:, 1] = np.bincount(self.owner, weights=weights[self.flat], minlength=n)
        to_parent = np.zeros((n, 2))
        for level in self.levels[:0:-1]:
            to_parent[level] = np.logaddexp(edge[:, 0] + up[level, None, 0], edge[:, 1] + up[level, None, 1])
            np.add.at(up, self.parent[level], to_parent[level])
        belief = np.zeros((n, 2))
        joint = np.zeros((n, 2, 2))
        for i, level in enumerate(self.levels):
            if i:
                rest = belief[self.parent[level]] - to_parent[level]
                pair = rest[:, :, None] + edge[None] + up[level][:, None, :]
                pair -= pair.max(axis=(1, 2), keepdims=True)
                pair = np.exp(pair)
                pair /= pair.sum(axis=(1, 2), keepdims=True)
                joint[level] = pair
                down = np.logaddexp(rest[:, None, 0] + edge[0], rest[:, None, 1] + edge[1])
                belief[level] = up[level] + down
            else:
                belief[level] = up[level]
            belief[level] -= belief[level].max(axis=1, keepdims=True)
        p = np.exp(belief)
        return p[:, 1] / p.sum(axis=1), joint


@dataclass
class TreeModel:
    weights: np.ndarray
    edge: np.ndarray

    def texts(self, htmls: list[str | None]) -> list[str]:
        """Main text of each page."""
        pages = [parse(h or "") for h in htmls]
        forest = Forest(pages)
        keep = forest.marginals(self.weights, self.edge)[0] > 0.5 if pages else []
        return ["\n".join([text for v, text in page.blocks if keep[base + v]]) for page, base in zip(pages, forest.first)]


def fit(pages: list[tuple[str, set[str]]], steps: int = 300, rate: float = 0.3, decay: float = 2e-3) -> TreeModel:
    """Weights of most likelihood on labelled pages (html, texts of the blocks that are content)."""
    parsed = [parse(h) for h, _ in pages]
    forest = Forest(parsed)
    label = np.zeros(len(forest.count))
    for page, (_, content), base in zip(parsed, pages, forest.first):
        good, every = [0] * len(page.parent), page.own[:]
        for v, text in page.blocks:
            good[v] += len(text) * (text in content)
        for v in range(len(good) - 1, 0, -1):
            good[page.parent[v]] += good[v]
            every[page.parent[v]] += every[v]
        label[base:base + len(good)] = [g * 2 > e for g, e in zip(good, every)]
    below = np.flatnonzero(forest.parent >= 0)
    x, y = label[forest.parent[below]].astype(int), label[below].astype(int)
    seen_edge = np.zeros((2, 2))
    np.add.at(seen_edge, (x, y), 1)
    seen = np.bincount(forest.flat, weights=label[forest.owner], minlength=len(_FEATURES))
    w, e = np.zeros(len(_FEATURES)), np.zeros((2, 2))
    w2, e2 = np.full(len(w), 1e-6), np.full((2, 2), 1e-6)
    for _ in range(steps):
        p, joint = forest.marginals(w, e)
        dw = (seen - np.bincount(forest.flat, weights=p[forest.owner], minlength=len(w))) / len(pages) - decay * w
        de = (seen_edge - joint[below].sum(axis=0)) / len(pages) - decay * e
        w2, e2 = w2 + dw * dw, e2 + de * de
        w, e = w + rate * dw / np.sqrt(w2), e + rate * de / np.sqrt(e2)
    return TreeModel(w, e)


def labelled_pages(n: int = 500, seed: int = 7) -> list[tuple[str, set[str]]]:
    """Pages with known article text, from plans of the usual kinds of layout."""
    r = random.Random(seed)
    syllables = "ba ce di fo gu la me ni po ru sa te vi zo ar en is on ul".split()

    def sentence(lo=4, hi=18):
        return " ".join("".join(r.choices(syllables, k=r.randint(1, 4))) for _ in range(r.randint(lo, hi))).capitalize() + "."

    def para(lo=1, hi=7):
        return " ".join(sentence() for _ in range(r.randint(lo, hi)))

    def links(k, tag="li"):
        return "".join(f'<{tag}><a href="/x{i}">{sentence(1, 2)[:-1]}</a></{tag}>' for i in range(k))

    def pick(*names):
        return r.choice(names)

    def noise():
        c = r.choice
        return c([
            lambda: f"<nav><ul>{links(r.randint(2, 9))}</ul></nav>",
            lambda: f'<div class="{pick("menu", "navbar", "main-nav", "breadcrumbs")}"><ul>{links(r.randint(2, 9))}</ul></div>',
            lambda: f"<header><div class='{pick('logo', 'site-title')}'>{sentence(1, 3)}</div>{pick('', f'<p>{sentence()}</p>', f'<nav>{links(4, 'div')}</nav>')}</header>",
            lambda: f'<div id="{pick("header", "masthead", "top-bar")}"><p>{sentence(2, 6)}</p></div>',
            lambda: f'<div class="{pick("ad", "ads", "advert", "sponsored", "promo-box", "banner-ad")}">{pick(para(1, 2), f"<p>{para(1, 3)}</p>")}</div>',
            lambda: f'<aside>{pick(para(1, 3), f"<h3>{sentence(1, 3)}</h3><p>{para(1, 3)}</p>", f"<ul>{links(5)}</ul>")}</aside>',
            lambda: f'<div class="{pick("sidebar", "related", "widget", "right-rail")}"><h3>{sentence(1, 4)}</h3>{pick(f"<ul>{links(5)}</ul>", f"<p>{para(1, 3)}</p>")}</div>',
            lambda: f'<div class="{pick("cookie-banner", "notice", "consent", "newsletter", "alert")}"><p>{para(1, 2)}</p>{pick("", "<button>Ok</button>")}</div>',
            lambda: f'<form action="/s"><label>{sentence(1, 3)}</label><input name="q"><button>{sentence(1, 1)}</button>{pick("", f"<p>{sentence()}</p>")}</form>',
            lambda: f'<div class="{pick("share", "social")}">{links(3, "span")}</div>',
            lambda: f'<div role="{pick("dialog", "banner", "complementary", "contentinfo", "search", "alert")}"><p>{para(1, 3)}</p></div>',
            lambda: f'<div {pick("hidden", 'aria-hidden="true"', 'style="display:none"')}><p>{para(1, 4)}</p></div>',
            lambda: f'<section class="{pick("hidden", "print-only", "search-form", "login-box", "contact-form")}"><p>{para(1, 3)}</p></section>',
            lambda: f"<dialog><p>{para(1, 2)}</p></dialog>",
        ])()

    def comments():
        each = "".join(pick(f'<div class="comment"><p>{para(1, 4)}</p></div>', f"<li><p>{para(1, 4)}</p></li>", f"<article class='comment'><p>{para(1, 3)}</p></article>", f"<p>{para(1, 3)}</p>") for _ in range(r.randint(1, 5)))
        return f'<{(t := pick("div", "section", "ul", "aside"))} {pick("class", "id")}="{pick("comments", "comment-list", "reader-comments", "responses", "discussion")}">{pick("", f"<h2>{sentence(1, 3)}</h2>")}{each}</{t}>'

    out = []
    for _ in range(n):
        content: list[str] = []

        def add(text):
            content.append(text)
            return text

        body = pick(f"<h1>{add(sentence(2, 9))}</h1>", f"<h1>{add(sentence(2, 9))}</h1>", "")
        tiny = r.random() < 0.2
        if tiny:
            body += f"<p>{pick('', '<b>')}{add(pick(sentence(1, 4)[:-1], sentence(2, 6), sentence(4, 9)))}{pick('<br>', '</p>')}"
        for _ in range(0 if tiny else r.randint(1, 12)):
            body += r.choices([
                lambda: f"<p>{add(para())}</p>",
                lambda: f"<p>{add(sentence(1, 4))}</p>",
                lambda: f"<p>{add(sentence(3, 8))}<br><p>{add(para())}</p>",
                lambda: f"<h2>{add(sentence(1, 5))}</h2>",
                lambda: "<ul>" + "".join(f"<li>{add(sentence(2, 9))}</li>" for _ in range(3)) + "</ul>",
                lambda: f"<blockquote><p>{add(para(1, 2))}</p></blockquote>",
                lambda: f"<table><tr><td>{add(sentence(1, 4))}</td><td>{add(sentence(1, 4))}</td></tr></table>",
                lambda: f"<div>{add(para(1, 3))}</div>",
                lambda: f"<section><h2>{add(sentence(1, 4))}</h2><p>{add(para())}</p></section>",
                lambda: noise() if r.random() < 0.3 else "",
            ], weights=[9, 1.5, 1, 2, 1, 1, 0.5, 1, 1, 1])[0]()
        if not content:
            body += f"<p>{add(para())}</p>"
        o, c = r.choices([("<article>", "</article>"), ("<main>", "</main>"), ("<main><article>", "</article></main>"), ('<div id="content">', "</div>"), ('<div class="post-body">', "</div>"), ('<div class="article-text"><div>', "</div></div>"), ("<section>", "</section>"), ("<div>", "</div>")], weights=[6, 2, 2, 2, 2, 1, 0.6, 0.6])[0]
        before = "".join(noise() for _ in range(r.randint(0, 4)))
        after = "".join(noise() for _ in range(r.randint(0, 3))) + (comments() if r.random() < 0.35 else "") + (r.choice([lambda: f"<footer>{sentence(2, 9)}</footer>", lambda: f"<footer><p>{para(1, 3)}</p><ul>{links(3)}</ul></footer>", lambda: f'<div class="footer"><p>{para(1, 2)}</p></div>', lambda: ""])())
        inside = comments() if r.random() < 0.08 else ""
        page = f"<!DOCTYPE html><html><head><title>{sentence()}</title></head><body>{before}{o}{body}{inside}{c}{after}</body></html>"
        out.append((page, set(content)))
    return out


@lru_cache(maxsize=1)
def trained() -> TreeModel:
    return fit(labelled_pages())


def extract(pages: DataFrame, html: str = "html", keep: tuple[str, ...] = ("page_id", "url"), model: TreeModel | None = None) -> DataFrame:
    """``keep``, the main ``text`` of every page (empty if none) and its length ``n_chars``.

    A null or empty page has an empty text; broken markup never fails, and a page
    is read once from end to end, so the time is linear in its length.  Narrow:
    each page is handled alone, in batches of bounded size, so repeated rows and
    long pages need no care.
    """
    model = model or trained()
    names = [*keep]
    source = pages.select(*names, F.col(html).alias("__html"))
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema if f.name in names] + ["text string", "n_chars long"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in arrowkit.slices(batches, "__html", 1 << 20):
            texts = model.texts(part.column("__html").to_pylist())
            yield pa.RecordBatch.from_arrays([*[part.column(c) for c in names], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=[*names, "text", "n_chars"])

    return source.mapInArrow(arrowkit.tidy(run), schema)
