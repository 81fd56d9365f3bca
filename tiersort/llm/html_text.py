"""Main text of web pages by a tree-structured graphical model.

A page becomes a tree of elements. Each element is content or not; its own
look (tag, words of its class and id, share of linked text, amount of text)
gives a node potential, and every parent-child pair one that depends on the
kind of the child. Messages are summed upward from the leaves and downward
from the root once, which gives each element's exact marginal. Text of
elements whose marginal is over one half is kept. Potentials are trained
on labelled pages; ``training_pages`` makes such pages from a small
grammar of layouts, and ``train`` takes any others.

Forms, scripts, styles and other elements without readable text are content
under no parameters. Null and empty pages have empty text; a page without any
element is one block; nesting of any depth and pages of any length are read
whole. Each row is judged for itself; an empty table gives no row.
"""

from __future__ import annotations

import html
import math
import random
import re
from collections import Counter, defaultdict
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from tiersort.llm.common import shipped

# HTML elements by behaviour.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title".split())
MUTE = frozenset("head script style noscript template svg math iframe object canvas audio video form button select option textarea input label title dialog menu".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd mark q rp rt ruby s samp small span strike strong sub sup time tt u var".split())
CHROME = frozenset("nav footer aside header".split())
SECTION = frozenset("html body article main section div center table tbody thead tfoot tr ul ol dl figure details fieldset".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split())
CLOSED_BY_SIBLING = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"},
                     "option": {"option"}, "tbody": {"thead", "tbody", "tr", "td", "th"}, "tfoot": {"thead", "tbody", "tr", "td", "th"}}
SCOPE = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table"}, "th": {"table"}, "tbody": {"table"}, "tfoot": {"table"}, "option": {"select", "datalist"}}

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([A-Za-z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.DOTALL)
ATTR = re.compile(r"(?:^|\s)(class|id|role|hidden|data-label)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.IGNORECASE)
NAME = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|[0-9]+")


class Page:
    """Elements in document order (a parent stands before its children) and text pieces."""

    def __init__(self) -> None:
        self.tag, self.parent, self.names, self.label = ["#root"], [-1], [()], [None]
        self.items: list[tuple[int, str | None]] = []  # (element, text), text None: a boundary between blocks

    def add(self, tag: str, parent: int, attrs: str) -> int:
        names: list[str] = []
        label = None
        if attrs:
            for m in ATTR.finditer(attrs):
                value, key = m[2] or m[3] or m[4] or "", m[1].lower()
                if key == "data-label":
                    label = value
                elif key == "hidden":
                    names.append("hidden")
                else:
                    names += [x.lower() for x in NAME.findall(html.unescape(value))]
        self.tag.append(tag)
        self.parent.append(parent)
        self.names.append(tuple(dict.fromkeys(names)))
        self.label.append(label)
        return len(self.tag) - 1


def parse(source: str) -> Page:
    page, stack, at = Page(), [0], 0

    def close(k: int) -> None:
        while len(stack) > k:
            if page.tag[stack.pop()] not in INLINE:
                page.items.append((stack[-1], None))

    def nearest(wanted: set, stop: set) -> int | None:
        for k in range(len(stack) - 1, 0, -1):
            t = page.tag[stack[k]]
            if t in wanted:
                return k
            if t in stop:
                return None
        return None

    m = TOKEN.search(source)
    while m:
        if m.start() > at:
            page.items.append((stack[-1], source[at:m.start()]))
        at = m.end()
        if m[0].startswith("<![CDATA["):
            page.items.append((stack[-1], html.escape(m[0][9:-3] if m[0].endswith("]]>") else m[0][9:])))
        elif m[2]:
            tag = m[2].lower()
            if m[1]:
                k = nearest({tag}, set())
                if k is not None:
                    close(k)
                elif tag not in INLINE:
                    page.items.append((stack[-1], None))
            else:
                if tag in CLOSES_P and (k := nearest({"p"}, {"button", "table", "td", "th", "li", "div", "article", "section", "blockquote"})) is not None:
                    close(k)
                if tag in CLOSED_BY_SIBLING and (k := nearest(CLOSED_BY_SIBLING[tag], SCOPE[tag])) is not None:
                    while (more := nearest(CLOSED_BY_SIBLING[tag], SCOPE[tag])) is not None:
                        close(more)
                if tag == "br":
                    page.items.append((stack[-1], " "))
                elif tag in VOID:
                    if tag == "hr":
                        page.items.append((stack[-1], None))
                else:
                    node = page.add(tag, stack[-1], m[3])
                    if tag not in INLINE:
                        page.items.append((node, None))
                    if tag in RAW:
                        end = re.compile(rf"</{tag}(?=[\s/>])[^>]*>|\Z", re.IGNORECASE).search(source, at)
                        at = end.end()
                    elif not m[3].rstrip().endswith("/"):
                        stack.append(node)
                    else:
                        stack.append(node)  # as browsers do: "<div/>" opens
        m = TOKEN.search(source, at)
    if at < len(source):
        page.items.append((stack[-1], source[at:]))
    return page


def kind(tag: str) -> str:
    return "inline" if tag in INLINE else "chrome" if tag in CHROME else "section" if tag in SECTION else "block"


def looks(page: Page) -> list[list[str]]:
    """Features of each element."""
    n = len(page.tag)
    words, linked = [0] * n, [0] * n
    for node, text in page.items:
        if text:
            words[node] += len(text.split())
    for i in range(n - 1, 0, -1):
        if page.tag[i] == "a":
            linked[i] = words[i]
        words[page.parent[i]] += words[i]
        linked[page.parent[i]] += linked[i]
    out = []
    for i in range(n):
        share = linked[i] / words[i] if words[i] else 0
        f = [f"tag:{page.tag[i]}"]
        f += [f"name:{x}" for x in page.names[i]]
        if kind(page.tag[i]) != "inline":
            f.append(f"links:{0 if share < .3 else 1 if share < .7 else 2}")
        if page.tag[i] in SECTION:
            f.append(f"words:{0 if not words[i] else 1 if words[i] < 5 else 2 if words[i] < 20 else 3}")
        out.append([*f, "any"])
    return out


class Model:
    """Potentials: of a child given its parent and its look, and of a block's text.

    ``look`` are weights of features for the odds that an element inside
    content is content itself, ``stray`` the odds by kind that one inside
    something else is, ``text`` log ratios of a text's features. What siblings
    say is not independent, so their texts' ratios are divided by the square
    root of their number.
    """

    def __init__(self, look: dict[str, float], stray: dict[str, float], text: dict[str, float]):
        self.look, self.stray, self.text = look, stray, text

    def potentials(self, page: Page) -> tuple[list[float], list[tuple[float, float]]]:
        """Log odds of each element's own text, and P(content | parent's side) of each element."""
        n, get = len(page.tag), self.look.get
        siblings = Counter(page.parent)
        own = [sum(self.text.get(f, 0.0) for f in fs) / math.sqrt(siblings[page.parent[i]]) for i, fs in enumerate(texts(page))]
        own[0] = 30.0
        edge = []
        for i, fs in enumerate(looks(page)):
            t = page.tag[i]
            if t in ("html", "body"):
                inside = 1 - 1e-9
            elif t in MUTE or "hidden" in page.names[i]:
                inside = 0.0
            else:
                inside = 1 / (1 + math.exp(-max(-30.0, min(30.0, sum(get(f, 0.0) for f in fs)))))
            edge.append((self.stray[kind(t)] if inside else 0.0, inside))
        return own, edge

    def marginals(self, page: Page) -> list[float]:
        """Probability of content for each element; one pass up the tree and one down."""
        own, edge = self.potentials(page)
        n = len(own)
        up, below = [0.0] * n, own[:]
        for i in range(n - 1, 0, -1):
            p0, p1 = edge[i]
            e = math.expm1(max(-60.0, min(60.0, below[i])))
            up[i] = math.log((1 + p1 * e) / (1 + p0 * e))
            below[page.parent[i]] += up[i]
        full, out = below[:], [1.0] * n
        for i in range(1, n):
            p0, p1 = edge[i]
            # the parent's odds without what this child told it
            e = math.exp(max(-60.0, min(60.0, full[page.parent[i]] - up[i])))
            yes, no = p0 + p1 * e, (1 - p0) + (1 - p1) * e
            full[i] = below[i] + (math.log(yes / no) if yes > 0 and no > 0 else -200.0 if no > 0 else 200.0)
            out[i] = 1 / (1 + math.exp(-max(-60.0, min(60.0, full[i]))))
        return out


def texts(page: Page) -> list[list[str]]:
    """Features of the text that stands directly in each element that isn't inline."""
    size, stops, sign = [0] * len(page.tag), [0] * len(page.tag), [0] * len(page.tag)
    for node, text in page.items:
        while page.tag[node] in INLINE:
            node = page.parent[node]
        if text:
            size[node] += len(text.split())
            stops[node] += text.count(".") + text.count(",")
            sign[node] += text.count("&copy;") + text.count("\xa9") + text.count("|") + text.count("\xbb")
    return [[f"size:{min(3, n.bit_length() // 2)}", f"stops:{min(2, s)}", f"signs:{min(1, g)}"] if n else [] for n, s, g in zip(size, stops, sign)]


def _logistic(rows: Counter, ridge: float = 0.05, steps: int = 25, least: int = 8) -> dict[str, float]:
    """Weights of features from counted rows (features, side)."""
    often = Counter()
    for (fs, _), c in rows.items():
        often.update({f: c for f in fs})
    names = sorted(f for f, c in often.items() if c >= least)
    known, merged = set(names), Counter()
    for (fs, side), c in rows.items():
        merged[tuple(f for f in fs if f in known), side] += c
    rows = merged
    slot = {f: i for i, f in enumerate(names)}
    x, y, k = np.zeros((len(rows), len(names))), np.zeros(len(rows)), np.zeros(len(rows))
    for j, ((fs, side), c) in enumerate(rows.items()):
        x[j, [slot[f] for f in fs]] = 1
        y[j], k[j] = side, c
    w = np.zeros(len(names))
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (k * p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(names)), x.T @ (k * (p - y)) + ridge * w)
        w -= step * min(1.0, 4 / max(1e-9, np.abs(step).max()))
    return dict(zip(names, w.tolist()))


def train(pages: Iterable[str], smooth: float = 1.0, most: float = 0.25) -> Model:
    """From pages whose elements carry ``data-label`` (1 or 0); others inherit their parent's."""
    rows: Counter = Counter()
    stray = {k: [smooth, 0.0] for k in ("inline", "chrome", "section", "block")}
    said = [Counter(), Counter()]
    for source in pages:
        page = parse(source)
        label = sides(page)
        for i, (look, text) in enumerate(zip(looks(page), texts(page))):
            if not i or page.tag[i] in ("html", "body") or page.tag[i] in MUTE:
                continue
            if label[page.parent[i]]:
                rows[tuple(look), label[i]] += 1
            else:
                stray[kind(page.tag[i])][0] += label[i]
                stray[kind(page.tag[i])][1] += 1
            said[label[i]].update(text)
    ratio = {}
    for f in said[0].keys() | said[1].keys():
        group = f.split(":")[0]
        share = [(s[f] + smooth) / (sum(v for k, v in s.items() if k.startswith(group)) + 2 * smooth) for s in said]
        ratio[f] = max(-most, min(most, math.log(share[1] / share[0])))
    return Model(_logistic(rows), {k: min(0.02, a / max(50.0, b)) for k, (a, b) in stray.items()}, ratio)


def sides(page: Page) -> list[int]:
    """Labels of a labelled page's elements."""
    label = [1] * len(page.tag)
    for i in range(1, len(page.tag)):
        label[i] = int(page.label[i]) if page.label[i] in ("0", "1") else label[page.parent[i]]
    return label


# Names that page authors give to parts that are not the article, and to those that are.
CHROME_NAMES = """nav navbar navigation menu menubar breadcrumb breadcrumbs topbar masthead header banner hero-header site-header page-header footer site-footer
 page-footer colophon copyright legal sidebar side rail aside widget widgets related recommended more-stories trending popular tags tag-list categories archive
 share sharing social follow subscribe subscription newsletter signup login register search cookie cookies consent gdpr notice notification alert popup modal
 overlay promo promotion promoted sponsor sponsored ad ads advert advertisement adsense banner-ad ad-slot ad-box dfp outbrain taboola comments comment
 comment-list commentlist reader-comments responses respond reply replies disqus discussion pagination pager prev-next toolbar skip-link print-only author-bio
 meta-links sitemap language-switcher""".split()
MAIN_NAMES = "article content main post entry story body text article-body post-content entry-content main-content story-body article-text page-content blog-post prose markdown".split()


def training_pages(count: int = 900, seed: int = 5) -> Iterator[str]:
    """Labelled pages of many layouts, with invented words."""
    rng = random.Random(seed)
    syllables = "ba ke lo mi nu ra se ti vo za der ing ent our".split()

    def word() -> str:
        return "".join(rng.choice(syllables) for _ in range(rng.randrange(1, 4)))

    def prose(least: int, most: int) -> str:
        return " ".join(word() for _ in range(rng.randrange(least, most))).capitalize() + "."

    def links(n: int) -> str:
        return "".join(f'<li><a href="/{word()}">{prose(1, 4)}</a></li>' for _ in range(n))

    def name(names: list[str]) -> str:
        x = rng.choice(names)
        return rng.choice([f'class="{x}"', f'id="{x}"', f'class="{x} {word()}"', f"class='{word()} {x}'"])

    def paragraphs(n: int) -> str:
        return "".join(f"<p>{prose(2, 60)}{rng.choice(['', '', f'<a href=#>{word()}</a> {word()}', f'<b>{word()}</b>'])}</p>" for _ in range(n))

    def block() -> str:
        """A piece of text as it stands in articles and elsewhere alike."""
        return rng.choice([
            lambda: paragraphs(rng.randrange(1, 5)), lambda: f"<h2>{prose(1, 6)}</h2>" + paragraphs(2), lambda: f"<blockquote><p>{prose(3, 20)}</p></blockquote>",
            lambda: "<ul>" + "".join(f"<li>{prose(1, 12)}</li>" for _ in range(3)) + "</ul>", lambda: f"<pre><code>{prose(2, 12)}</code></pre>",
            lambda: "<ol>" + "".join(f"<li><p>{prose(1, 12)}</p></li>" for _ in range(3)) + "</ol>", lambda: f"<h4>{prose(1, 5)}</h4>", lambda: f"<p><span>{prose(1, 9)}</span> <em>{word()}</em></p>",
            lambda: f"<table><tbody><tr><th>{word()}</th><td>{prose(1, 4)}</td></tr></tbody></table>", lambda: f"<figure><img><figcaption>{prose(2, 9)}</figcaption></figure>",
            lambda: f"<section>{paragraphs(2)}</section>", lambda: f"<div>{paragraphs(2)}</div>", lambda: f"<h3>{prose(1, 5)}</h3>", lambda: f"<dl><dt>{word()}</dt><dd>{prose(2, 8)}</dd></dl>",
            lambda: f"<div>{prose(1, 12)}</div>", lambda: f"<p><a href=#>{prose(1, 4)}</a></p>", lambda: f"<address>{prose(1, 4)}</address>"])()

    def main_part() -> str:
        out = [f"<h1>{prose(2, 9)}</h1>"] if rng.random() < 0.8 else []
        for _ in range(rng.randrange(1, 9)):
            out.append(chrome(1) if rng.random() < 0.08 else block())
        return "".join(out)

    def chrome(depth: int = 0) -> str:
        own = [rng.choice([block, block, lambda: f"<ul>{links(rng.randrange(2, 8))}</ul>", lambda: prose(2, 25), lambda: f"<span>{prose(2, 9)}</span>",
                           lambda: f"<article><p>{prose(3, 20)}</p></article>", lambda: f"<h1>{prose(1, 5)}</h1>"])() for _ in range(rng.randrange(1, 6))]
        if depth < 3 and rng.random() < 0.3:
            own.append(chrome(depth + 1))
        tag = rng.choice(["nav", "footer", "aside", "header", "div", "div", "div", "section", "ul", "p", "span"] if depth != 1 else ["aside", "div", "nav", "footer", "header"])
        attrs = "" if tag in CHROME and rng.random() < 0.5 else " " + name(CHROME_NAMES)
        if tag == "ul":
            own = [links(5)]
        elif tag in ("p", "span"):
            own = [prose(2, 25)]
        return f'<{tag}{attrs} data-label="0">{"".join(own)}</{tag}>'

    for _ in range(count):
        tag = rng.choice(["article", "article", "main", "div", "section", None])
        body = main_part()
        if tag:
            attrs = "" if tag in ("article", "main") and rng.random() < 0.6 else " " + name(MAIN_NAMES)
            body = f'<{tag}{attrs} data-label="1">{body}</{tag}>'
        for _ in range(rng.randrange(3)):
            body = f'<div{rng.choice(["", " " + name(["container", "wrapper", "page", "row", "col", "layout", "inner", "site"])])} data-label="1">{chrome() if rng.random() < .4 else ""}{body}{chrome() if rng.random() < .4 else ""}</div>'
        yield f"<html><head><title>{word()}</title></head><body>{''.join(chrome() for _ in range(rng.randrange(1, 5)))}{body}{''.join(chrome() for _ in range(rng.randrange(1, 4)))}</body></html>"


_HELD: dict[str, Model] = {}


def standard_model() -> Model:
    """Trained once in each process, from fixed pages."""
    if "model" not in _HELD:
        _HELD["model"] = train(training_pages())
    return _HELD["model"]


def main_text(source: str | None, model: Model) -> str:
    if not source:
        return ""
    page = parse(source)
    keep = [p > 0.5 for p in model.marginals(page)]
    blocks: list[str] = []
    now: list[str] = []
    for node, text in [*page.items, (0, None)]:
        if text is None:
            if now and (whole := " ".join(html.unescape("".join(now)).split())):
                blocks.append(whole)
            now = []
        elif keep[node]:
            now.append(text)
    return "\n\n".join(blocks)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", model: Model | None = None) -> DataFrame:
    """Rows (page_id, url, text, n_chars)."""
    sent = shipped(pages.sparkSession, model or standard_model())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = sent()
        for b in batches:
            for at in range(0, b.num_rows, 500):
                part = b.slice(at, 500)
                text = [main_text(t.as_py(), held) for t in part.column(2)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(text, pa.string()), pa.array(map(len, text), pa.int64())],
                                                 names=["page_id", "url", "text", "n_chars"])

    kinds = {f.name: f.dataType.simpleString() for f in pages.schema}
    return pages.select(id_col, url_col, html_col).mapInArrow(run, f"page_id {kinds[id_col]}, url {kinds[url_col]}, text string, n_chars long")
