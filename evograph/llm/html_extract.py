"""Main text of HTML pages: a linear-chain conditional random field over DOM leaf blocks.

A page is read into leaf blocks: stretches of text between block-level tags, each with the
open elements around it. A block's features are its ancestors' tags and the words of their
class, id and role attributes, and measures of its text (length, share of link text,
punctuation, marks such as a copyright sign, place in the page). The chain has two labels,
main text and other; neighbouring labels have weights of their own; Viterbi decodes a page.

The weights are fitted here on labelled pages from a seeded generator that varies layout,
containers, class names and language, so no page of a corpus is needed or learnt.

Text of main blocks: references decoded, white space folded to single spaces and trimmed,
blocks joined by one newline in page order. Null or empty html gives an empty text. Markup
need not be well formed: unknown ends are ignored, open elements close with their parents,
an unfinished tag is text. Only raw text (``RAW``) is dropped unread, up to its end tag or, as
browsers do, to the end of the page; one that closes itself is empty. Drawings, formulas and
fallback content are read: their text belongs to the line around them, and a block-level
element ends a drawing or formula left open. Repeated rows give repeated results, other columns are ignored.
Only one page at a time is held; a page's size is not limited.
"""

from __future__ import annotations

import html as html_lib
import math
import random
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from evograph.llm.common import table

# fixed values: element kinds of the HTML standard
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr b bdi bdo br cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr svg math canvas object".split())
RAW = frozenset("script style iframe textarea title noembed noframes xmp".split())
FOREIGN = frozenset({"svg", "math"})
#: An opening one of these ends an open element of the listed kinds within the nearest container.
IMPLIED_END = {
    **{t: frozenset({"p"}) for t in "address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split()},
    "li": frozenset({"li", "p"}), "dt": frozenset({"dt", "dd", "p"}), "dd": frozenset({"dt", "dd", "p"}),
    "tr": frozenset({"tr", "td", "th", "p"}), "td": frozenset({"td", "th", "p"}), "th": frozenset({"td", "th", "p"}), "option": frozenset({"option"}),
}
_SCOPE = frozenset("html body article aside blockquote details div dl fieldset figure footer form header main menu nav ol section table ul".split())

_KEYS = _SCOPE | frozenset().union(*IMPLIED_END.values())
_MARKUP = re.compile(r"<!--|<!\[CDATA\[|<[!?]|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)")
#: The rest of a tag; no part can be matched in two ways, so a failure costs one pass.
_REST = re.compile(r"(?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+>")
#: Open elements that a block's features look at, nearest first.
NEAREST = 64
_ATTR = re.compile(r"(?:^|[\s\"'/])(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_NAME = re.compile(r"[a-z]+")
_HIDDEN = re.compile(r"(?:^|\s)hidden(?:\s|=|$)|display\s*:\s*none", re.I)
MAIN, OTHER = 1, 0


def _tokens(page: str) -> Iterator[tuple[int, int, str, str, str]]:
    """Start, end, slash, name and attributes of every piece of markup in one pass; other markup has no name.

    A tag with an unclosed quotation ends at its next ``>``; after the last ``>`` all is text.
    """
    at, last = 0, page.rfind(">")
    while m := _MARKUP.search(page, at):
        start, kind = m.start(), m[0]
        if kind == "<!--" or kind == "<![CDATA[":
            close = "-->" if kind == "<!--" else "]]>"
            end = page.find(close, m.end())
            at = len(page) if end < 0 else end + len(close)
            yield start, at, "", "", ""
            continue
        if start > last:
            return
        rest = None if m[2] is None else _REST.match(page, m.end())
        at = rest.end() if rest else page.find(">", start) + 1
        yield start, at, m[1] or "", (m[2] or "").lower(), page[m.end() : at - 1] if m[2] else ""


class _Open:
    """Open elements; what has to be known of all of them is kept up as they come and go."""

    def __init__(self) -> None:
        self.items: list[tuple[str, tuple[str, ...], bool, int, int]] = []  # tag, words, hidden, drawing around, last container
        self.count: dict[str, int] = {}

    def push(self, tag: str, words: tuple[str, ...], hidden: bool) -> None:
        _, _, above, drawing, key = self.items[-1] if self.items else ("", (), False, -1, -1)
        here = len(self.items)
        drawing = here if tag in FOREIGN else -1 if tag == "foreignobject" else drawing
        self.items.append((tag, words, hidden or above, drawing, here if tag in _KEYS else key))
        self.count[tag] = self.count.get(tag, 0) + 1

    def cut(self, k: int) -> None:
        """Close the element at ``k`` and all inside it."""
        for tag, *_ in self.items[k:]:
            self.count[tag] -= 1
        del self.items[k:]

    def close(self, tag: str) -> None:
        if self.count.get(tag):
            k = len(self.items) - 1
            while self.items[k][0] != tag:
                k -= 1
            self.cut(k)

    def drawing(self) -> int:
        """Where the drawing or formula begins that we are in; -1 for none."""
        return self.items[-1][3] if self.items else -1

    def imply(self, ends: frozenset[str]) -> None:
        """Close the nearest of ``ends`` inside the nearest container."""
        k = self.items[-1][4] if self.items else -1
        while k >= 0:
            tag = self.items[k][0]
            if tag in ends:
                self.cut(k)
                return
            if tag in _SCOPE or k == 0:
                return
            k = self.items[k - 1][4]

    def ancestors(self) -> tuple:
        near = self.items[: -NEAREST - 1 : -1]
        return tuple((tag, words) for tag, words, *_ in reversed(near) if tag not in INLINE)


def blocks(page: str | None) -> list[tuple[str, tuple, float, bool]]:
    """Leaf blocks: text, ancestors as (tag, words), share of link text, whether it is hidden. One pass over the page."""
    out: list[tuple[str, tuple, float, bool]] = []
    stack, text, linked = _Open(), [], 0

    def flush() -> None:
        nonlocal linked
        if text:
            t = " ".join(html_lib.unescape("".join(text)).split())
            if t:
                out.append((t, stack.ancestors(), min(1.0, linked / len(t)), bool(stack.items) and stack.items[-1][2]))
            text.clear()
        linked = 0

    def add(s: str) -> None:
        nonlocal linked
        if s:
            text.append(s)
            if stack.count.get("a"):
                linked += len(s.strip())

    page, at = page or "", 0
    for start, end, slash, tag, attributes in _tokens(page):
        if start < at:  # inside raw text
            continue
        add(page[at:start])
        at = end
        if not tag:
            continue
        if tag in IMPLIED_END and not slash and (k := stack.drawing()) >= 0:
            stack.cut(k)
        inside = stack.drawing() >= 0
        if inside:
            text.append(" ")
        if slash:
            if tag not in INLINE and (not inside or tag in IMPLIED_END):
                flush()
            stack.close(tag)
            continue
        if tag == "br":
            text.append(" ")
            continue
        if tag not in INLINE and not inside:
            flush()
            if tag in IMPLIED_END:
                stack.imply(IMPLIED_END[tag])
        empty = attributes.rstrip().endswith("/")
        if tag in RAW and not empty:
            close = re.compile(rf"</{tag}\s*>", re.I).search(page, at)
            at = close.end() if close else len(page)
            continue
        if tag in VOID or tag in RAW or empty:
            continue
        words: list[str] = []
        for a in _ATTR.finditer(attributes):
            words += _NAME.findall((a[2] or a[3] or a[4] or "").lower())
        stack.push(tag, tuple(words), tag == "template" or bool(_HIDDEN.search(attributes)))
    add(page[at:])
    flush()
    return out


def features(page: list[tuple[str, tuple, float, bool]]) -> list[list[str]]:
    """Names of the features of every block."""
    out, n, seen = [], len(page), set()
    for k, (t, anc, link, hidden) in enumerate(page):
        tags = {tag for tag, _ in anc}
        words = {w for _, ws in anc for w in ws}
        n_words = t.count(" ") + 1
        f = ["bias", *(f"tag:{x}" for x in tags), *(f"word:{x}" for x in words)]
        f.append(f"leaf:{anc[-1][0] if anc else '-'}")
        f.append(f"size:{min(7, int(math.log2(n_words)))}")
        f.append(f"link:{0 if link == 0 else 1 if link < 0.3 else 2 if link < 0.8 else 3}")
        f.append("end:" + ("stop" if t[-1] in ".!?…。" else "other"))
        f.append(f"commas:{min(3, t.count(','))}")
        if "©" in t or "copyright" in t.lower():
            f.append("mark:copyright")
        if "|" in t or "»" in t or "›" in t:
            f.append("mark:bar")
        if "@" in t or "http" in t:
            f.append("mark:address")
        if hidden:
            f.append("hidden")
        if not (tags & {"article", "main"}):
            f.append("outside")
        if not words:
            f.append("plain")
        if k == 0:
            f.append("first")
        if k == n - 1:
            f.append("last")
        if t in seen:
            f.append("again")
        seen.add(t)
        out.append(f)
    return out


class ChainModel:
    """Weights of a two-label chain: one score per feature, and of neighbouring labels."""

    def __init__(self, weights: dict[str, float], same: tuple[float, float, float, float]):
        self.weights, self.pair = weights, same  # pair: (other, other), (other, main), (main, other), (main, main)

    def scores(self, feats: list[list[str]]) -> list[float]:
        get = self.weights.get
        return [sum([get(x, 0.0) for x in f]) for f in feats]

    def viterbi(self, scores: list[float]) -> list[int]:
        oo, om, mo, mm = self.pair
        a, b, back = 0.0, scores[0], []
        for s in scores[1:]:
            to_o, to_m = (a + oo, 0) if a + oo >= b + mo else (b + mo, 1), (a + om, 0) if a + om > b + mm else (b + mm, 1)
            back.append((to_o[1], to_m[1]))
            a, b = to_o[0], to_m[0] + s
        y = [1 if b > a else 0]
        for step in reversed(back):
            y.append(step[y[-1]])
        return y[::-1]


def _log_add(a: float, b: float) -> float:
    m = a if a > b else b
    return m + math.log1p(math.exp(-abs(a - b)))


def fit(pages: list[tuple[list[list[str]], list[int]]], epochs: int = 12, rate: float = 0.3, decay: float = 1e-4, seed: int = 7) -> ChainModel:
    """Maximum likelihood by adaptive gradient steps, one page at a time (forward and backward sums)."""
    w: dict[str, float] = {}
    grad2: dict[str, float] = {}
    pair, pair2 = [0.0] * 4, [1e-8] * 4
    rng, order = random.Random(seed), list(range(len(pages)))
    for _ in range(epochs):
        rng.shuffle(order)
        for p in order:
            feats, gold = pages[p]
            s = [sum([w.get(x, 0.0) for x in f]) for f in feats]
            n = len(s)
            fo, fm = [0.0], [s[0]]
            for k in range(1, n):
                fo.append(_log_add(fo[-1] + pair[0], fm[-1] + pair[2]))
                fm.append(_log_add(fo[k - 1] + pair[1], fm[-1] + pair[3]) + s[k])
            bo, bm = [0.0] * n, [0.0] * n
            for k in range(n - 2, -1, -1):
                bo[k] = _log_add(pair[0] + bo[k + 1], pair[1] + s[k + 1] + bm[k + 1])
                bm[k] = _log_add(pair[2] + bo[k + 1], pair[3] + s[k + 1] + bm[k + 1])
            z = _log_add(fo[-1], fm[-1])
            for k in range(n):
                g = gold[k] - math.exp(fm[k] + bm[k] - z)
                if abs(g) > 1e-4:
                    for x in feats[k]:
                        d = g - decay * w.get(x, 0.0)
                        grad2[x] = grad2.get(x, 1e-8) + d * d
                        w[x] = w.get(x, 0.0) + rate * d / math.sqrt(grad2[x])
            gp = [0.0] * 4
            for k in range(1, n):
                gp[2 * gold[k - 1] + gold[k]] += 1
                for i, (f, tail) in enumerate(((fo[k - 1], bo[k]), (fo[k - 1], s[k] + bm[k]), (fm[k - 1], bo[k]), (fm[k - 1], s[k] + bm[k]))):
                    gp[i] -= math.exp(f + pair[i] + tail - z)
            for i in range(4):
                d = gp[i] / n - decay * pair[i]
                pair2[i] += d * d
                pair[i] += rate * d / math.sqrt(pair2[i])
    return ChainModel(w, tuple(pair))


class PageMaker:
    """Labelled pages: ``page()`` gives html in which main text and other text are known."""

    MENUS = ("nav", "menu", "navigation", "navbar", "breadcrumb", "breadcrumbs", "topnav", "tabs", "pagination", "pager")
    HEADS = ("header", "masthead", "banner", "topbar", "branding", "logo", "site")
    FEET = ("footer", "foot", "copyright", "legal", "colophon", "bottom")
    SIDES = ("sidebar", "aside", "related", "widget", "popular", "trending", "recommended", "more", "rail", "tags", "share", "social", "author")
    ADS = ("ad", "ads", "advert", "advertisement", "sponsor", "sponsored", "promo", "promotion", "banner")
    NOTES = ("cookie", "notice", "consent", "alert", "gdpr", "popup", "modal", "overlay", "subscribe", "newsletter", "signup", "paywall", "disclaimer")
    TALKS = ("comment", "comments", "reply", "replies", "discussion", "disqus", "respond", "reader", "feedback", "reviews")
    BODIES = ("content", "article", "post", "entry", "story", "body", "text", "main")

    def __init__(self, seed: int):
        self.r = random.Random(seed)

    def words(self, n: int) -> str:
        """Words of random letters of one of several scripts; their letters are no features."""
        r = self.r
        letters = r.choice(("abcdefghiklmnoprstuvw", "αβγδεζηθικλμνοπρστυφω", "абвгдежзиклмнопрстуя"))
        out = ["".join(r.choice(letters) for _ in range(r.randint(1, 11))) for _ in range(n)]
        for k in range(n):
            if r.random() < 0.08:
                out[k] += r.choice(",;:")
        s = " ".join(out)
        return s[:1].upper() + s[1:]

    def sentence(self, lo: int, hi: int) -> str:
        r = self.r
        t = self.words(r.randint(lo, hi)) + r.choice((".", ".", ".", "", "!", "?", ":"))
        return t.replace(" ", " &amp; ", 1) if r.random() < 0.05 else t

    def attrs(self, names: tuple[str, ...], p: float = 0.9) -> str:
        r = self.r
        if r.random() > p:
            return ""
        w = r.choice(names)
        w = r.choice((w, w, f"{w}-{r.choice(('box', 'wrap', 'inner', 'list', 'area', 'main', 'item'))}", f"site-{w}", f"{w}{r.randint(1, 9)}", w.capitalize()))
        return f' {r.choice(("class", "class", "id"))}="{w}"'

    def links(self) -> str:
        r = self.r
        items = [f'<a href="/{k}">{self.words(r.randint(1, 3))}</a>' for k in range(r.randint(2, 8))]
        return r.choice((lambda: "<ul>" + "".join(f"<li>{x}</li>" for x in items) + "</ul>", lambda: " | ".join(items), lambda: "".join(f"<span>{x}</span> " for x in items)))()

    def prose(self, n: int) -> str:
        r = self.r
        out = []
        for _ in range(n):
            t = self.sentence(*r.choice(((1, 4), (5, 20), (20, 80))))
            if r.random() < 0.15:
                t += f' <a href="/x">{self.words(2)}</a> {self.sentence(3, 12)}'
            out.append(r.choice(("<p>{}</p>", "<p>{}</p>", "<p>{}</p>", "<div>{}</div>", "<p><em>{}</em></p>", "<p>{}")).format(t))
        return "".join(out)

    def main(self) -> str:
        r = self.r
        out = [f"<h1>{self.sentence(2, 14)}</h1>"] if r.random() < 0.85 else []
        for _ in range(r.choice((0, 1, 1, 2, 3, 5, 8))):
            out.append(r.choice((
                lambda: self.prose(r.randint(1, 4)), lambda: self.prose(r.randint(1, 4)), lambda: f"<h2>{self.sentence(1, 8)}</h2>{self.prose(1)}",
                lambda: "<ul>" + "".join(f"<li>{self.sentence(1, 20)}</li>" for _ in range(r.randint(2, 5))) + "</ul>",
                lambda: f"<blockquote>{self.prose(1)}</blockquote>", lambda: f"<pre>{self.sentence(4, 20)}</pre>",
                lambda: "<table>" + "".join(f"<tr><td>{self.words(2)}</td><td>{self.words(1)}</td></tr>" for _ in range(3)) + "</table>",
                lambda: f"<figure><img src=x><figcaption>{self.sentence(3, 12)}</figcaption></figure>",
            ))())
        return "".join(out) or f"<p>{self.sentence(5, 30)}</p>"

    def other(self, kind: str) -> str:
        r = self.r
        body = lambda: self.prose(r.randint(1, 3)) if r.random() < 0.6 else self.sentence(2, 30)
        if kind == "menu":
            return r.choice((f"<nav{self.attrs(self.MENUS, 0.5)}>{self.links()}</nav>", f"<div{self.attrs(self.MENUS, 1)}>{self.links()}</div>", f"<ul{self.attrs(self.MENUS, 1)}><li>{self.words(2)}</li><li>{self.words(1)}</li></ul>"))
        if kind == "head":
            return r.choice((f"<header{self.attrs(self.HEADS, 0.5)}>{body()}{self.links()}</header>", f"<div{self.attrs(self.HEADS, 1)}>{body()}</div>"))
        if kind == "foot":
            t = f"&copy; {self.words(2)} &middot; {self.sentence(3, 30)}" if r.random() < 0.6 else body()
            return r.choice((f"<footer{self.attrs(self.FEET, 0.4)}>{t}</footer>", f"<div{self.attrs(self.FEET, 1)}><p>{t}</p></div>"))
        if kind == "side":
            return r.choice((f"<aside{self.attrs(self.SIDES, 0.5)}>{body()}{self.links()}</aside>", f"<div{self.attrs(self.SIDES, 1)}><h3>{self.words(2)}</h3>{body()}</div>", f"<section{self.attrs(self.SIDES, 1)}>{self.links()}</section>"))
        if kind == "form":
            return f"<form{self.attrs(self.NOTES, 0.3)}><label>{self.sentence(1, 8)}</label><input type=text><p>{self.sentence(2, 20)}</p><button>{self.words(1)}</button></form>"
        names = {"ad": self.ADS, "note": self.NOTES, "talk": self.TALKS}[kind]
        tag = r.choice(("div", "div", "section", "p" if kind == "ad" else "div"))
        inner = self.sentence(3, 30) if tag == "p" else body()
        if kind == "talk" and r.random() < 0.6:
            inner = "".join(f'<div{self.attrs(self.TALKS, 0.7)}><b>{self.words(1)}</b><p>{self.sentence(3, 40)}</p></div>' for _ in range(r.randint(1, 4)))
            inner = r.choice(("", f"<h3>{self.words(2)}</h3>")) + inner
        if kind == "talk" and r.random() < 0.3:
            inner = f"<ol><li>{inner}</li></ol>"
        return f"<{tag}{self.attrs(names, 1)}>{inner}</{tag}>"

    def page(self) -> list[tuple[str, int]]:
        """Parts of html with their label: markup that opens or closes containers has none (-1)."""
        r = self.r
        out: list[tuple[str, int]] = [(f"<!DOCTYPE html><html><head><title>{self.words(4)}</title><style>p{{}}</style></head><body>", -1)]
        wrap = r.random() < 0.4
        if wrap:
            out.append((f'<div class="{r.choice(("page", "wrapper", "container", "site", "layout"))}">', -1))
        for kind, p in (("note", 0.25), ("head", 0.5), ("menu", 0.8), ("ad", 0.4), ("side", 0.2)):
            if r.random() < p:
                out.append((self.other(kind), 0))
        opening = r.choice(("<article>", "<article>", "<main>", "<main><article>", f"<article{self.attrs(self.BODIES, 1)}>", f"<div{self.attrs(self.BODIES, 1)}>", f"<section{self.attrs(self.BODIES, 1)}>", '<div role="main">'))
        names = re.findall(r"<(\w+)", opening)
        out.append((opening, -1))
        for k in range(r.randint(1, 3)):
            out.append((self.main(), 1))
            kind = r.choice(("ad", "side", "form", "note", "talk"))
            if r.random() < 0.2:
                out.append((self.other(kind), 0))
        closing = "".join(f"</{n}>" for n in reversed(names))
        if r.random() < 0.3:
            out += [(self.other("talk"), 0), (closing, -1)]
        else:
            out.append((closing, -1))
        for kind, p in (("talk", 0.35), ("side", 0.4), ("form", 0.2), ("ad", 0.2), ("menu", 0.15), ("note", 0.2), ("foot", 0.85)):
            if r.random() < p:
                out.append((self.other(kind), 0))
        if wrap:
            out.append(("</div>", -1))
        return [*out, ("</body></html>", -1)]

    def labelled(self) -> tuple[str, list[list[str]], list[int]]:
        """A page, the features of its blocks and their labels."""
        parts = self.page()
        # private-use marks carry the label through the reader, then leave the text
        marked = "".join(re.sub(r">([^<>]*[^<>\s])", lambda m: f">{chr(0xE000 + label)}{m[1]}", html) if label >= 0 else html for html, label in parts)
        got, gold = [], []
        for t, anc, link, hidden in blocks(marked):
            label = 1 if "\ue001" in t else 0
            clean = " ".join(t.replace("\ue000", "").replace("\ue001", "").split())
            if clean:
                got.append((clean, anc, link, hidden))
                gold.append(label)
        return "".join(h for h, _ in parts), features(got), gold


TRAINING_PAGES = 600
_MODEL: list[ChainModel] = []


def model(pages: int = TRAINING_PAGES, seed: int = 11) -> ChainModel:
    """The fitted model; made once in a process."""
    if not _MODEL:
        maker = PageMaker(seed)
        data = [(f, y) for _, f, y in (maker.labelled() for _ in range(pages)) if f]
        _MODEL.append(fit(data))
    return _MODEL[0]


def main_text(page: str | None, m: ChainModel) -> str:
    got = blocks(page)
    if not got:
        return ""
    return "\n".join(t for (t, *_), y in zip(got, m.viterbi(m.scores(features(got)))) if y == MAIN)


def extract(pages: DataFrame, m: ChainModel | None = None) -> DataFrame:
    """``page_id, url, text, n_chars`` of every page."""
    m = m or model()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(0, batch.num_rows, 256):
                part = batch.slice(k, 256)
                texts = [main_text(x.as_py(), m) for x in part.column(2)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array(np.array([len(t) for t in texts], dtype=np.int64))], ["page_id", "url", "text", "n_chars"])

    return pages.select("page_id", "url", "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")


def op10_html_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
