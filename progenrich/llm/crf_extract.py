"""Main text of web pages by a linear-chain conditional random field over DOM leaf blocks.

A forgiving tokenizer turns a page into leaf blocks: runs of text between block-level tags, each with its
ancestors. Features are ancestor tags, words of their class, id and role, and measures of the text. The
field has two labels (main, other); it is trained on pages that are generated with labels in many layouts
(``training_pages``), and pages are decoded by Viterbi.
"""

from __future__ import annotations

import html as html_lib
import random
import re
from collections import Counter
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_slices

# Fixed lists of HTML element names.
#: Their content is no text of the page: scripts, styles, inert markup, and what only form controls show.
RAW = frozenset("script style template iframe textarea select title head".split())
BLOCK = frozenset(
    "html body main article section header footer nav aside div p ul ol li dl dt dd h1 h2 h3 h4 h5 h6 blockquote pre figure figcaption table thead tbody tfoot tr td th caption form fieldset legend "
    "address details summary hr center dialog menu label button input option noscript".split()
)
VOID = frozenset("br hr img input meta link area base col embed source track wbr".split())
#: Opening one of these closes an open one of the listed kinds, up to a container.
IMPLIED = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}}
ENDS_P = BLOCK - {"p", "label", "button", "input", "option", "html", "body"}
CONTAINERS = frozenset("article section main div nav aside header footer form table ul ol dl body blockquote".split())

#: A tag from its "<" on, with quoted values; possessive, so that a failure costs one look at each character.
_TAG = re.compile(r"<(/?)([A-Za-z][^\s/>]*+)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>")
_NAME = re.compile(r"<(/?)([A-Za-z][^\s/>]*+)")
#: Deepest nesting that is told apart; elements below it belong to the element at that depth.
DEPTH = 512
_ATTR = re.compile(r"(?:^|[\s\"'])(?:class|id|role|aria-label)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_WORD = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")
MARK = ""


class Path:
    """An open element: its own features and the element around it. Blocks of one element share it."""

    __slots__ = ("tag", "own", "up", "weight")

    def __init__(self, tag: str, own: tuple[str, ...], up: Path | None):
        self.tag, self.own, self.up, self.weight = tag, own, up, None

    def features(self) -> list[str]:
        """Features of all elements, innermost first, and the innermost tag as such."""
        out, at = ["in " + self.own[0]], self
        while at is not None:
            out += at.own
            at = at.up
        return out


@dataclass
class Block:
    text: str
    path: Path | None
    links: int  # characters inside links


@lru_cache(maxsize=50_000)
def _element(tag: str, attrs: str) -> tuple[str, ...]:
    """Features of one ancestor: its tag, and the words of its class, id and role."""
    words = {w.lower() for m in _ATTR.finditer(attrs) for w in _WORD.findall(m[1] or m[2] or m[3] or "")}
    return (f"<{tag}>", *sorted(f".{w}" for w in words))


class _Reader:
    """Reads a page forwards; what was looked for in vain is not looked for again, so broken markup costs no more."""

    def __init__(self, page: str):
        self.page, self.missing = page, set()
        self.effort = 8 * len(page) + 1000  # characters that failed looks at quoted values may cost in all

    def find(self, what: str, at: int) -> int:
        if what in self.missing:
            return -1
        i = self.page.find(what, at)
        if i < 0:
            self.missing.add(what)
        return i

    def after_closing(self, tag: str, at: int) -> int:
        """Position behind the closing tag, or -1."""
        if tag in self.missing:
            return -1
        m = re.compile(rf"</{re.escape(tag)}(?=[\s/>])[^>]*+>", re.I).search(self.page, at)
        if m is None:
            self.missing.add(tag)
            return -1
        return m.end()

    def tag(self, at: int) -> tuple[bool, str, str, int] | None:
        """(closing, name, attributes, position behind) of the tag at "<"; none if no ">" follows."""
        if self.effort > 0:
            m = _TAG.match(self.page, at)
            if m:
                return bool(m[1]), m[2].lower(), m[3], m.end()
            self.effort -= len(self.page) - at
        end = self.find(">", at)  # a quote that is never closed: the tag ends at the first ">"
        if end < 0:
            return None
        m = _NAME.match(self.page, at)
        return bool(m[1]), m[2].lower(), self.page[m.end() : end], end + 1


def blocks(page: str) -> list[Block]:
    """Leaf blocks in page order; the text has its references decoded and single spaces."""
    out: list[Block] = []
    stack: list[Path] = []
    opened: Counter[str] = Counter()  # open elements by tag
    deeper: Counter[str] = Counter()  # elements that lie too deep to be told apart, by tag
    run: list[str] = []
    reader, linked, in_link, at, n = _Reader(page), 0, 0, 0, len(page)

    def close() -> None:
        nonlocal run, linked
        if run:
            text = " ".join(html_lib.unescape("".join(run)).split())
            if text:
                out.append(Block(text, stack[-1] if stack else None, linked))
            run, linked = [], 0

    def text_of(piece: str) -> None:
        nonlocal linked
        if piece:
            run.append(piece)
            if in_link:
                linked += len(piece)

    def leave(i: int) -> None:
        for p in stack[i:]:
            opened[p.tag] -= 1
        del stack[i:]

    def imply(kinds) -> None:
        if not any(opened[k] for k in kinds):
            return
        for i in range(len(stack) - 1, -1, -1):
            if stack[i].tag in kinds:
                leave(i)
                return
            if stack[i].tag in CONTAINERS:
                return

    while at < n:
        i = page.find("<", at)
        if i < 0:
            text_of(page[at:])
            break
        text_of(page[at:i])
        nxt = page[i + 1 : i + 2]
        if nxt in ("!", "?"):
            kind = "-->" if page.startswith("<!--", i) else "]]>" if page.startswith("<![CDATA[", i) else ">"
            end = reader.find(kind, i + 2)
            if end < 0 and kind == "-->":
                end = reader.find("--!>", i + 2)
            at = end + len(kind) if end >= 0 else n
            continue
        if not (nxt.isascii() and nxt.isalpha()) and not (nxt == "/" and page[i + 2 : i + 3].isascii() and page[i + 2 : i + 3].isalpha()):
            if nxt == "/" and page[i + 2 : i + 3]:  # no name after "</": a comment up to ">"
                end = reader.find(">", i)
                at = end + 1 if end >= 0 else n
            else:
                text_of("<")
                at = i + 1
            continue
        found = reader.tag(i)
        if found is None:  # the end of the page cuts the tag off
            break
        closing, tag, attrs, at = found
        alone = attrs.endswith("/") or (attrs == "" and page[at - 2] == "/")
        if closing:
            if tag == "a":
                in_link = max(0, in_link - 1)
            elif tag in BLOCK:
                close()
                if deeper[tag]:
                    deeper[tag] -= 1
                elif opened[tag]:
                    leave(next(k for k in range(len(stack) - 1, -1, -1) if stack[k].tag == tag))
            continue
        if tag in RAW and not alone:
            if tag == "head":
                body = reader.after_closing("head", at)
                starts = reader.find("<body", at) if body < 0 else page.find("<body", at, body)
                at = starts if starts >= 0 else body if body >= 0 else at
            else:
                end = reader.after_closing(tag, at)
                at = end if end >= 0 else (n if tag in ("script", "style") else at)
            continue
        if tag == "br":
            text_of(" ")
        elif tag == "a":
            in_link += 1
        elif tag in BLOCK:
            close()
            if tag in ENDS_P or tag == "p":
                imply(IMPLIED.get(tag, set()) | {"p"})
            if tag not in VOID and not alone:
                if len(stack) < DEPTH:
                    stack.append(Path(tag, _element(tag, attrs), stack[-1] if stack else None))
                    opened[tag] += 1
                else:
                    deeper[tag] += 1
    close()
    return out


def measures(b: Block) -> list[str]:
    """Features of the text itself."""
    n = len(b.text)
    share = b.links / max(1, n)
    words = b.text.count(" ") + 1
    ends = sum(b.text.count(c) for c in ".!?")
    return [
        f"size{min(6, n.bit_length() - 4 if n >= 16 else 0)}",
        f"link{0 if share < 0.1 else 1 if share < 0.5 else 2 if share < 0.9 else 3}",
        f"stops{0 if not ends else 1 if ends < words / 12 else 2}",
        "sign" if "©" in b.text or "(c)" in b.text.lower() else "nosign",
        "bar" if "|" in b.text or "»" in b.text or "·" in b.text else "nobar",
        "bias",
    ]


# Words by which layouts name their parts (fixed lists for the generated training pages).
MAIN_NAMES = "content article post entry story main text body page wrapper container column primary inner".split()
OTHER_NAMES = {
    "nav": "nav menu navigation navbar breadcrumb breadcrumbs topnav links".split(),
    "header": "header masthead banner branding logo top toolbar".split(),
    "footer": "footer bottom copyright colophon legal site".split(),
    "aside": "sidebar aside widget related recommended popular trending more share social tags rail".split(),
    "notice": "notice cookie cookies consent gdpr alert popup modal warning message overlay".split(),
    "ad": "ad ads advert advertisement sponsor sponsored promo promotion adsense banner".split(),
    "form": "form login signup subscribe newsletter search contact".split(),
    "comments": "comments comment reply replies discussion respond disqus commentlist feedback".split(),
}
_SYLLABLES = "ba de ki lo mu na per qui ros sta ter un ver wen xi yo zar en ion ment lich que el ung".split()


def training_pages(count: int = 500, seed: int = 11) -> list[str]:
    """Pages in varied layouts whose main text runs begin with a private mark."""
    rng = random.Random(seed)

    def words(lo: int, hi: int, stops: bool = True) -> str:
        out, left = [], rng.randint(lo, hi)
        while left > 0:
            k = min(left, rng.randint(3, 14))
            s = " ".join("".join(rng.choice(_SYLLABLES) for _ in range(rng.randint(1, 4))) for _ in range(k))
            out.append(s.capitalize() + (rng.choice([".", ".", ".", "!", "?", ""]) if stops else ""))
            left -= k
        return " ".join(out).replace("a", rng.choice(["a", "é", "ä"]))

    def named(kind: str) -> str:
        if rng.random() < 0.15:
            return ""
        name = rng.choice(OTHER_NAMES[kind])
        if rng.random() < 0.3:
            name = f"{rng.choice(['site', 'page', 'top', 'main', 'js', 'c'])}-{name}"
        return f' {rng.choice(["class", "class", "id"])}="{name}"'

    def link(text: str) -> str:
        return f'<a href="/{rng.randint(1, 999)}">{text}</a>'

    def other(kind: str) -> str:
        tag = {"nav": "nav", "header": "header", "footer": "footer", "aside": "aside", "form": "form"}.get(kind, "div")
        if rng.random() < 0.35:
            tag = rng.choice(["div", "section"])
        attr = named(kind)
        if tag in ("div", "section") and not attr:
            attr = f' class="{rng.choice(OTHER_NAMES[kind])}"'
        if kind == "nav":
            inner = "<ul>" + "".join(f"<li>{link(words(1, 3, False))}</li>" for _ in range(rng.randint(2, 9))) + "</ul>"
        elif kind == "header":
            inner = rng.choice([f"<p>{words(2, 8, False)}</p>", link(words(1, 4, False)), f"<div>{words(2, 6)}</div><h2>{words(1, 4, False)}</h2>"])
        elif kind == "footer":
            inner = rng.choice(["&copy; ", "&copy; 2020 ", ""]) + rng.choice([words(3, 20), f"{words(1, 3, False)} &middot; {words(3, 40)}", f"<p>{words(5, 30)}</p>" + link(words(1, 2, False))])
        elif kind == "aside":
            inner = f"<h3>{words(1, 4, False)}</h3>" + "".join(rng.choice([f"<p>{words(4, 30)}</p>", f"<li>{link(words(2, 8, False))}</li>"]) for _ in range(rng.randint(1, 5)))
        elif kind == "comments":
            one = lambda: f"<{(t := rng.choice(['div', 'li', 'article'] if rng.random() < 0.3 else ['div', 'li']))} class=\"comment\"><p>{words(4, 60)}</p></{t}>"
            inner = f"<h3>{words(1, 3, False)}</h3>" + "".join(one() for _ in range(rng.randint(1, 5)))
        elif kind == "form":
            inner = f"<label>{words(1, 3, False)}</label><input name=q><button>{words(1, 2, False)}</button><p>{words(2, 10)}</p>"
        else:
            inner = rng.choice([words(2, 40), f"<p>{words(4, 40)}</p>", f"<p>{words(3, 12)}</p><button>{words(1, 1, False)}</button>"])
        return f"<{tag}{attr}>{inner}</{tag}>"

    def main() -> list[str]:
        title = f"<h1>{MARK}{words(2, 12, False)}</h1>"
        parts = [title if rng.random() < 0.85 else ""]
        for _ in range(rng.choice([1, 1, 2, 3, 4, 6, 9, 14])):
            kind, body = rng.random(), MARK + words(1, rng.choice([6, 40, 120]))
            if kind < 0.7:
                parts.append(f"<p>{'<b>' * (rng.random() < 0.2)}{body}{'</p>' * (rng.random() < 0.85)}")
            elif kind < 0.78:
                parts.append(f"<h2>{MARK}{words(1, 7, False)}</h2>")
            elif kind < 0.86:
                parts.append("<ul>" + "".join(f"<li>{MARK}{words(2, 15)}</li>" for _ in range(rng.randint(1, 5))) + "</ul>")
            elif kind < 0.92:
                parts.append(f"<blockquote>{body}</blockquote>")
            elif kind < 0.96:
                parts.append(f"<p>{body} {link(words(1, 4, False))}. {words(3, 20)}</p>")
            else:
                parts.append(f"<table><tr><td>{MARK}{words(1, 4, False)}</td><td>{MARK}{words(1, 4, False)}</td></tr></table>")
        if rng.random() < 0.2:
            parts.insert(rng.randint(1, len(parts)), other(rng.choice(["ad", "aside", "form"])))
        return parts

    pages = []
    for i in range(count):
        tag, attr = rng.choice([("article", ""), ("article", ""), ("article", ' class="{}"'), ("main", ""), ("div", ' class="{}"'), ("div", ' id="{}"'), ("section", ' class="{}"')])
        attr = attr.format(rng.choice(MAIN_NAMES))
        inner = "".join(main())
        if rng.random() < 0.15:
            inner += other("comments")
        body = f"<{tag}{attr}>{inner}" + f"</{tag}>" * (rng.random() < 0.95)
        if rng.random() < 0.35:
            w = rng.choice(["div", "main", "section"])
            body = f'<{w} class="{rng.choice(MAIN_NAMES)}">{body}{other("aside") if rng.random() < 0.4 else ""}</{w}>'
        before = [other(k) for k in ("header", "nav", "notice", "ad", "form") if rng.random() < (0.75 if k == "nav" else 0.4)]
        after = [other(k) for k in ("comments", "aside", "ad", "form", "notice", "footer") if rng.random() < (0.8 if k == "footer" else 0.3)]
        pages.append(f"<!DOCTYPE html><html><head><title>{words(2, 9, False)}</title></head><body>{''.join(before)}{body}{''.join(after)}</body></html>")
    return pages


@dataclass
class Field:
    """Weights for the label ``main`` against ``other``: a log-odds for each feature, and transitions."""

    weights: dict[str, float]
    start: tuple[float, float]
    step: tuple[tuple[float, float], tuple[float, float]]

    def __post_init__(self):
        #: Weights of elements seen before, by their features.
        self._own: dict[tuple[str, ...], float] = {}

    def _of(self, own: tuple[str, ...]) -> float:
        s = self._own.get(own)
        if s is None:
            if len(self._own) > 50_000:
                self._own.clear()
            s = self._own[own] = sum(self.weights.get(f, 0.0) for f in own)
        return s

    def emission(self, b: Block) -> float:
        w, p = self.weights, b.path
        s = 0.0
        if p is not None:
            todo, at = [], p
            while at is not None and at.weight is None:  # elements are weighed once, outermost first
                todo.append(at)
                at = at.up
            total = at.weight if at is not None else 0.0
            for x in reversed(todo):
                total = x.weight = total + self._of(x.own)
            s = p.weight + w.get("in " + p.own[0], 0.0)
        return s + sum(w.get(f, 0.0) for f in measures(b))

    def decode(self, found: list[Block]) -> list[bool]:
        """Viterbi labels of a page's blocks."""
        if not found:
            return []
        (a00, a01), (a10, a11) = self.step
        e = self.emission(found[0])
        v0, v1 = self.start[0], self.start[1] + e
        back: list[tuple[bool, bool]] = []
        for b in found[1:]:
            e = self.emission(b)
            f0, f1 = v1 + a10 > v0 + a00, v1 + a11 > v0 + a01
            back.append((f0, f1))
            v0, v1 = (v1 + a10 if f0 else v0 + a00), (v1 + a11 if f1 else v0 + a01) + e
        label = v1 > v0
        out = [label]
        for f0, f1 in reversed(back):
            label = f1 if label else f0
            out.append(label)
        return out[::-1]


def block_features(b: Block) -> list[str]:
    return [*(b.path.features() if b.path else []), *measures(b)]


def train(pages: list[str], steps: int = 250, decay: float = 2e-3, least: int = 3) -> Field:
    """Maximum likelihood by gradient steps on the field's log-likelihood, all pages at once."""
    seqs = []
    for p in pages:
        found = blocks(p)
        seqs.append([(block_features(Block(b.text.replace(MARK, ""), b.path, b.links)), MARK in b.text) for b in found])
    seqs = [s for s in seqs if s]
    count: dict[str, int] = {}
    for s in seqs:
        for fs, _ in s:
            for f in set(fs):
                count[f] = count.get(f, 0) + 1
    index = {f: i for i, f in enumerate(sorted(f for f, n in count.items() if n >= least))}
    long, n = max(map(len, seqs)), len(seqs)
    x = np.zeros((n, long, len(index)), np.float32)
    y, live = np.zeros((n, long)), np.zeros((n, long))
    for i, s in enumerate(seqs):
        for t, (fs, main) in enumerate(s):
            live[i, t], y[i, t] = 1, main
            for f in fs:
                if f in index:
                    x[i, t, index[f]] += 1
    flat = x.reshape(n * long, -1)
    theta = np.zeros(len(index) + 6)
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    yi = y.astype(int)
    for k in range(1, steps + 1):
        w, start, step = theta[:-6], theta[-6:-4], theta[-4:].reshape(2, 2)
        e = np.stack([np.zeros((n, long)), (flat @ w).reshape(n, long)], 2)
        alpha, beta = np.zeros((n, long, 2)), np.zeros((n, long, 2))
        alpha[:, 0] = start + e[:, 0]
        for t in range(1, long):
            new = np.logaddexp(alpha[:, t - 1, :1] + step[0], alpha[:, t - 1, 1:] + step[1]) + e[:, t]
            alpha[:, t] = np.where(live[:, t, None] > 0, new, alpha[:, t - 1])
        for t in range(long - 2, -1, -1):
            nxt = beta[:, t + 1] + e[:, t + 1]
            new = np.logaddexp(nxt[:, :1] + step[:, 0], nxt[:, 1:] + step[:, 1])
            beta[:, t] = np.where(live[:, t + 1, None] > 0, new, 0)
        z = np.logaddexp(alpha[:, -1, 0], alpha[:, -1, 1])
        p1 = np.exp(alpha[:, :, 1] + beta[:, :, 1] - z[:, None]) * live
        grad = np.zeros_like(theta)
        grad[:-6] = flat.T @ (y * live - p1).reshape(-1)
        first = np.exp(alpha[:, 0] + beta[:, 0] - z[:, None])
        grad[-6:-4] = np.bincount(yi[:, 0], minlength=2) - first.sum(0)
        pair = live[:, 1:]
        for a in (0, 1):
            for b in (0, 1):
                expect = np.exp(np.minimum(alpha[:, :-1, a] + step[a, b] + e[:, 1:, b] + beta[:, 1:, b] - z[:, None], 0)) * pair
                grad[-4 + 2 * a + b] = ((yi[:, :-1] == a) * (yi[:, 1:] == b) * pair).sum() - expect.sum()
        g = grad / n - decay * theta
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        theta += 0.1 * (m / (1 - 0.9**k)) / (np.sqrt(v / (1 - 0.99**k)) + 1e-8)
    s, t = theta[-6:-4], theta[-4:]
    return Field({f: float(theta[i]) for f, i in index.items()}, (float(s[0]), float(s[1])), ((float(t[0]), float(t[1])), (float(t[2]), float(t[3]))))


@lru_cache(maxsize=2)
def trained(count: int = 500, seed: int = 11) -> Field:
    return train(training_pages(count, seed))


def main_text(page: str, field: Field) -> str:
    found = blocks(page)
    return " ".join(b.text for b, keep in zip(found, field.decode(found)) if keep)


def extract(pages: DataFrame, field: Field | None = None) -> DataFrame:
    """``page_id, url, text, n_chars`` of every page from its whole html.

    Null html counts as empty and gives an empty text; broken markup is read as far as it goes; repeated
    rows and null keys pass through; an empty table gives no rows; other columns are not read.
    """
    field = field or trained()

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = [main_text(h, field) if h else "" for h in batch["html"].to_pylist()]
        return pa.RecordBatch.from_arrays([batch["page_id"], batch["url"], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    picked = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return map_slices(picked, run, "page_id long, url string, text string, n_chars long", rows=64)
