"""Main text of web pages by a recurrent block labeller.

A page becomes the sequence of its leaf blocks, each with hashed features of its tag path (tags, classes, ids) and of its
words, and a few numbers. A small bidirectional LSTM in numpy reads the sequence from both sides and labels every block with the
whole page as context. It is trained here, on pages that a generator writes with their labels; no page of the table is used.
"""

from __future__ import annotations

import html
import math
import random
import re
import zlib
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biblake.llm.base import batch, over_batches, slices

# Elements of HTML.
BLOCKS = frozenset("html head title body p div section article main aside nav header footer ul ol li dl dt dd table thead tbody tfoot tr td th caption h1 h2 h3 h4 h5 h6 blockquote pre form fieldset legend figure figcaption address hr details summary dialog menu option select button center".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: A tag that opens ends these if they are open (up to the next list, table or section).
ENDS = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "body": {"head"}} | {t: {"p"} for t in BLOCKS - {"p", "li", "dt", "dd", "tr", "td", "th", "option", "body", "html", "head", "title"}}
FENCE = frozenset("ul ol dl table section article main aside nav header footer div form body html select".split())
_TAG = re.compile(
    r"<!--.*?(?:-->|\Z)|<(script|style|template|noscript|svg|iframe|textarea|object)\b[^>]*>.*?(?:</\1\s*>|\Z)"
    r"|<(/?)([a-z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*+)>|<(/?)([a-z][^\s/>]*)()[^>]*>|<[!?/][^>]*>",
    re.S | re.I,
)
_NAMES = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_PARTS = re.compile(r"[a-z]+")

PATHS, WORDS, NUMBERS, HIDDEN, UNITS = 1024, 64, 8, 24, 16


def _slot(kind: str, name: str, n: int) -> int:
    return zlib.crc32(f"{kind}:{name}".encode()) % n


@dataclass
class Block:
    text: str
    path: tuple[int, ...]
    linked: int


@dataclass
class _Node:
    tag: str
    path: tuple[int, ...]
    #: the slots of the element itself, as the innermost one
    leaf: tuple[int, ...] = field(default=())


@lru_cache(4096)
def _own(tag: str, attributes: str) -> tuple[tuple[int, ...], tuple[int, ...]]:
    names = [p for m in _NAMES.finditer(attributes) for p in _PARTS.findall((m[1] or m[2] or m[3] or "").lower())]
    if tag == "div" and not names:
        return (), (_slot("leaf", tag, PATHS),)
    slots = [_slot("in", tag, PATHS), *(_slot("name", x, PATHS) for x in names)]
    return tuple(slots), (_slot("leaf", tag, PATHS), *(_slot("own", x, PATHS) for x in names))


def blocks(page: str | None) -> list[Block]:
    """The page's leaf blocks in order: text between block-level tags, references decoded, white space as one space."""
    page = page or ""
    out: list[Block] = []
    stack = [_Node("", ())]
    text: list[str] = []
    links = linked = 0

    def close() -> None:
        nonlocal linked
        said = " ".join(html.unescape("".join(text)).split())
        if said:
            out.append(Block(said, tuple(sorted({*stack[-1].path, *stack[-1].leaf})), linked))
        text.clear()
        linked = 0

    at = 0
    for m in _TAG.finditer(page):
        if m.start() > at:
            text.append(page[at : m.start()])
            if links:
                linked += m.start() - at
        at = m.end()
        tag = (m[3] or m[6] or "").lower()
        if not tag:
            continue
        shut = bool(m[2] or m[5])
        if tag == "br":
            text.append(" ")
        elif tag == "a":
            links = 0 if shut else 1
        elif tag not in BLOCKS:
            continue
        elif shut:
            close()
            where = next((i for i in range(len(stack) - 1, 0, -1) if stack[i].tag == tag), 0)
            if where:
                del stack[where:]
            links = 0
        else:
            close()
            ends = ENDS.get(tag, ())
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag in ends:
                    del stack[i:]
                    break
                if stack[i].tag in FENCE:
                    break
            if tag not in VOID:
                into, leaf = _own(tag, m[4] or "")
                stack.append(_Node(tag, stack[-1].path + into, leaf))
    text.append(page[at:])
    close()
    return out


@lru_cache(50_000)
def _word_slot(word: str) -> int:
    return _slot("word", word.strip(".,:;!?()\"'"), WORDS)


def _many(text: str, letters: str) -> int:
    return sum(map(text.count, letters))


def inputs(page: list[Block]) -> np.ndarray:
    """(blocks, PATHS + WORDS + NUMBERS) features of a page."""
    x = np.zeros((len(page), PATHS + WORDS + NUMBERS), np.float32)
    n = len(page)
    for i, b in enumerate(page):
        row = x[i]
        row[list(b.path)] = 1.0
        ws = b.text.lower().split()
        #: the root of each slot's share of all the block's words
        row[PATHS : PATHS + WORDS] = np.sqrt(np.bincount([_word_slot(w) for w in ws], minlength=WORDS) / (len(ws) or 1))
        size = len(b.text)
        row[PATHS + WORDS :] = (
            math.log1p(size) / 6, math.log1p(len(ws)) / 5, min(1.0, b.linked / size), float(b.text[-1] in ".!?…\"”"),
            min(2.0, _many(b.text, ".,;:") / (len(ws) or 1)), _many(b.text, "0123456789") / size, i / n, math.log1p(n) / 6,
        )
    return x


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class Labeller:
    """Dense input layer, one LSTM in each direction, one logistic output a block."""

    def __init__(self, seed: int = 3):
        rng = np.random.default_rng(seed)
        draw = lambda a, b: (rng.standard_normal((a, b)) / math.sqrt(a)).astype(np.float32)
        self.w = {"in": draw(PATHS + WORDS + NUMBERS, HIDDEN) * 2, "in_b": np.zeros(HIDDEN, np.float32), "out": draw(2 * UNITS + HIDDEN, 1), "out_b": np.zeros(1, np.float32)}
        for d in "fb":
            bias = np.zeros(4 * UNITS, np.float32)
            bias[UNITS : 2 * UNITS] = 1.0  # remember at first
            self.w |= {f"x{d}": draw(HIDDEN, 4 * UNITS), f"h{d}": draw(UNITS, 4 * UNITS), f"b{d}": bias}

    def _run(self, z: np.ndarray, mask: np.ndarray, d: str):
        n, steps, _ = z.shape
        h, c = np.zeros((n, UNITS), np.float32), np.zeros((n, UNITS), np.float32)
        pre = z @ self.w[f"x{d}"] + self.w[f"b{d}"]
        out, kept = np.zeros((n, steps, UNITS), np.float32), [None] * steps
        for t in range(steps) if d == "f" else range(steps - 1, -1, -1):
            g = pre[:, t] + h @ self.w[f"h{d}"]
            i, f, o = _sigmoid(g[:, :UNITS]), _sigmoid(g[:, UNITS : 2 * UNITS]), _sigmoid(g[:, 2 * UNITS : 3 * UNITS])
            u = np.tanh(g[:, 3 * UNITS :])
            m = mask[:, t : t + 1]
            c2 = f * c + i * u
            q = np.tanh(c2)
            kept[t] = (h, c, i, f, o, u, q, m)
            c, h = m * c2 + (1 - m) * c, m * o * q + (1 - m) * h
            out[:, t] = h
        return out, kept

    def forward(self, x: np.ndarray, mask: np.ndarray):
        z = np.tanh(x @ self.w["in"] + self.w["in_b"])
        hf, kf = self._run(z, mask, "f")
        hb, kb = self._run(z, mask, "b")
        both = np.concatenate([hf, hb, z], axis=2)
        return (both @ self.w["out"] + self.w["out_b"])[:, :, 0], (z, both, kf, kb)

    def gradients(self, x: np.ndarray, y: np.ndarray, mask: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        score, (z, both, kf, kb) = self.forward(x, mask)
        p = _sigmoid(score)
        loss = -float((mask * (y * np.log(p + 1e-9) + (1 - y) * np.log(1 - p + 1e-9))).sum() / mask.sum())
        ds = ((p - y) * mask / mask.sum())[:, :, None].astype(np.float32)
        g = {"out": np.einsum("btk,bto->ko", both, ds), "out_b": ds.sum(axis=(0, 1))}
        dboth = ds @ self.w["out"].T
        dz = dboth[:, :, 2 * UNITS :].copy()
        for d, kept, dh_all in (("f", kf, dboth[:, :, :UNITS]), ("b", kb, dboth[:, :, UNITS : 2 * UNITS])):
            steps = x.shape[1]
            dh, dc = np.zeros((len(x), UNITS), np.float32), np.zeros((len(x), UNITS), np.float32)
            dpre = np.zeros((len(x), steps, 4 * UNITS), np.float32)
            gh = np.zeros_like(self.w[f"h{d}"])
            for t in range(steps - 1, -1, -1) if d == "f" else range(steps):
                h, c, i, f, o, u, q, m = kept[t]
                dh = dh + dh_all[:, t]
                live = m * dh
                dc2 = m * dc + live * o * (1 - q * q)
                da = np.concatenate([dc2 * u * i * (1 - i), dc2 * c * f * (1 - f), live * q * o * (1 - o), dc2 * i * (1 - u * u)], axis=1)
                dpre[:, t] = da
                gh += h.T @ da
                dh = (1 - m) * dh + da @ self.w[f"h{d}"].T
                dc = (1 - m) * dc + dc2 * f
            g |= {f"h{d}": gh, f"x{d}": np.einsum("bth,btg->hg", z, dpre), f"b{d}": dpre.sum(axis=(0, 1))}
            dz += dpre @ self.w[f"x{d}"].T
        da = dz * (1 - z * z)
        g |= {"in": np.einsum("btd,bth->dh", x, da), "in_b": da.sum(axis=(0, 1))}
        return loss, g

    def fit(self, pages: list[tuple[np.ndarray, np.ndarray]], rounds: int = 14, size: int = 32, rate: float = 0.01) -> Labeller:
        """Adam over mini-batches of pages of like length; deterministic."""
        rng = np.random.default_rng(5)
        m = {k: np.zeros_like(v) for k, v in self.w.items()}
        v = {k: np.zeros_like(x) for k, x in self.w.items()}
        step = 0
        order = sorted(range(len(pages)), key=lambda i: len(pages[i][0]))
        groups = [order[s : s + size] for s in range(0, len(order), size)]
        for r in range(rounds):
            for k in rng.permutation(len(groups)):
                x, mask, y = padded([pages[i][0] for i in groups[k]], [pages[i][1] for i in groups[k]])
                _, g = self.gradients(x, y, mask)
                norm = math.sqrt(sum(float((a * a).sum()) for a in g.values()))
                step += 1
                for name, a in g.items():
                    a = a / max(1.0, norm)
                    m[name] = 0.9 * m[name] + 0.1 * a
                    v[name] = 0.99 * v[name] + 0.01 * a * a
                    self.w[name] -= rate * (0.4 if r > rounds * 2 // 3 else 1) * (m[name] / (1 - 0.9**step)) / (np.sqrt(v[name] / (1 - 0.99**step)) + 1e-8)
        return self

    def keep(self, pages: list[np.ndarray], most: int = 6000) -> list[np.ndarray]:
        """For each page which blocks are main text. Pages of like length are run together, ``most`` padded blocks at a time."""
        out: list[np.ndarray] = [np.zeros(0, bool)] * len(pages)
        todo = sorted((i for i in range(len(pages)) if len(pages[i])), key=lambda i: len(pages[i]))
        while todo:
            n = max(1, min(len(todo), 64, most // len(pages[todo[-1]])))
            group, todo = todo[-n:], todo[:-n]
            x, mask, _ = padded([pages[i] for i in group])
            score, _ = self.forward(x, mask)
            for i, s in zip(group, score):
                out[i] = s[: len(pages[i])] > 0
        return out


def padded(xs: list[np.ndarray], ys: list[np.ndarray] | None = None):
    n = max(map(len, xs))
    x, mask, y = np.zeros((len(xs), n, xs[0].shape[1]), np.float32), np.zeros((len(xs), n), np.float32), np.zeros((len(xs), n), np.float32)
    for i, a in enumerate(xs):
        x[i, : len(a)], mask[i, : len(a)] = a, 1
        if ys is not None:
            y[i, : len(a)] = ys[i]
    return x, mask, y


class Writer:
    """Writes pages with their labels: text that begins with the mark is main text."""

    MARK = "⁠"
    SYLLABLES = "th an er on ti en ch le ou ré ion ver ge ein sch ung los que par ado ión es ci ra mo ka lo ni ta".split()
    MENU = "Home About Contact News Sports Login Register Search Shop Blog Help Archive Topics Video Careers Press Imprint Datenschutz Impressum Kontakt Accueil Inicio".split()
    SAYINGS = {
        "footer": ["© {y} {w} Ltd. All rights reserved.", "Privacy policy", "Terms of use", "Copyright {y} {w}", "Imprint and contact", "Powered by {w}", "© {w} · {s}", "{s}"],
        "ad": ["Sponsored", "Advertisement", "Buy now and save 50%!", "{s}", "Special offer: {w}", "{s}"],
        "notice": ["We use cookies to improve your experience.", "Accept all cookies", "By continuing you agree to our terms.", "Your browser is out of date.", "{s}"],
        "comments": ["{w} says:", "{s}", "Reply", "Great post, thanks!", "{s} {s}", "3 comments", "Posted {y}-03-12 by {w}"],
        "side": ["Related articles", "Most read", "{s}", "Subscribe to our newsletter", "Follow us", "Popular tags", "Share this", "{s}"],
        "form": ["Your e-mail", "Subscribe", "Send", "Leave a comment", "Name", "{s}"],
        "head": ["{w} daily", "The {w} Times", "{s}", "Welcome to {w}"],
        "meta": ["Posted on {y}-04-02 by {w}", "By {w} {w}", "{w} {w}, 12 May {y}", "Published {y}/07/09", "Filed under {w}, {w}", "Written by {w} on March 3, {y}", "5 min read"],
        "foot": ["Copyright {y} {w}", "Copyright {y} Webmaster", "Last updated {y}", "(c) {y} {w}", "Webmaster: {w}@example.com", "Best viewed at 800x600", "All rights reserved", "You are visitor number {y}"],
    }
    NAMES = {
        "nav": ["nav", "menu", "navbar", "navigation", "main-menu", "breadcrumb", "topnav", "links", "toc"],
        "footer": ["footer", "site-footer", "bottom", "copyright", "legal"],
        "ad": ["ad", "ads", "advert", "sponsored", "banner", "promo", "ad-slot", "advertisement"],
        "notice": ["cookie", "notice", "consent", "cookie-banner", "alert", "gdpr", "popup", "disclaimer"],
        "comments": ["comments", "comment", "discussion", "comment-list", "replies", "respond", "reader-comments"],
        "side": ["sidebar", "aside", "widget", "related", "social", "share", "newsletter", "recommended", "tags"],
        "form": ["form", "search", "login", "subscribe", "signup"],
        "head": ["header", "site-header", "masthead", "top", "branding", "logo"],
        "meta": ["meta", "byline", "post-meta", "date", "author", "postinfo", "entry-meta", "posted"],
        "wrap": ["wrap", "wrapper", "page", "container", "outer", "site", "layout"],
        "main": ["content", "article", "post", "entry", "story", "main", "article-body", "entry-content", "post-content", "text"],
    }
    TAGS = {"nav": "nav", "footer": "footer", "ad": "div", "notice": "div", "comments": "section", "side": "aside", "form": "form", "head": "header"}

    def __init__(self, seed: int):
        self.r = random.Random(seed)
        self.style = self.r.choice(("", "", "", "", "", "shout", "bars", "marks", "digits", "again"))

    def word(self) -> str:
        return "".join(self.r.choice(self.SYLLABLES) for _ in range(self.r.choice((1, 1, 2, 2, 3))))

    def sentence(self, least: int = 1, most: int = 20) -> str:
        """Some pages are written oddly throughout: in capitals, with bars between words or with marks after them."""
        ws = [self.word() for _ in range(self.r.randint(least, most))]
        ws[0] = ws[0].capitalize()
        if self.style == "shout":
            return "!! ".join(ws).upper() + "!!"
        if self.style == "bars":
            return " | ".join(ws)
        if self.style == "marks":
            return " ".join(w + self.r.choice(("###", "***", "%%%", "$$$", "&amp;&amp;&amp;", ",", "...", "")) for w in ws)
        if self.style == "again":
            return " ".join(ws[:1] * len(ws) + ws[: self.r.randint(0, 2)])
        if self.style == "digits":
            return " ".join(w if self.r.random() < 0.5 else str(self.r.randint(0, 99999)) for w in ws) + "."
        return " ".join(ws) + self.r.choice((".", ".", ".", "", "!", "?"))

    def saying(self, kind: str) -> str:
        return self.r.choice(self.SAYINGS[kind]).format(y=self.r.randint(1995, 2026), w=self.word().capitalize(), s=self.sentence(2, 14))

    def open(self, kind: str, semantic: bool) -> tuple[str, str]:
        r = self.r
        tag = self.TAGS[kind] if semantic else r.choice(("div", "section", "div"))
        name = "" if tag not in ("div", "section") and r.random() < 0.5 else f' {r.choice(("class", "class", "id"))}="{r.choice(self.NAMES[kind])}"'
        return f"<{tag}{name}>", f"</{tag}>"

    def chrome(self, kind: str) -> str:
        r = self.r
        a, b = self.open(kind, r.random() < 0.6)
        if kind == "nav":
            items = [r.choice(self.MENU) if r.random() < 0.5 else self.word() for _ in range(r.randint(2, 9))]
            body = "<ul>" + "".join(f'<li><a href="/{i}">{x}</a></li>' for i, x in enumerate(items)) + "</ul>" if r.random() < 0.7 else " | ".join(f'<a href="/{i}">{x}</a>' for i, x in enumerate(items))
        elif kind == "form":
            body = "".join(f"<label>{self.saying('form')}</label><input name=x>" if r.random() < 0.5 else f"<p>{self.saying('form')}</p>" for _ in range(r.randint(1, 3))) + f"<button>{self.saying('form')}</button>"
        else:
            wrap = r.choice(("p", "p", "", "li", "div", "a"))
            body = "".join(f'<a href="#">{s}</a> ' if wrap == "a" else f"<{wrap}>{s}</{wrap}>" if wrap else s + " " for s in (self.saying(kind) for _ in range(r.randint(1, 5))))
            if kind == "head" and r.random() < 0.3:
                body = f"<h1>{self.word()} {self.word()}</h1>" + body
        return a + body + b

    def main(self) -> str:
        r, mark = self.r, self.MARK
        out = []
        if r.random() < 0.9:
            h = f"<h1>{mark}{self.sentence(2, 12)}</h1>"
            out.append(f"<header>{h}</header>" if r.random() < 0.12 else h)
        for _ in range(r.randint(1, 14)):
            k = r.random()
            body = " ".join(self.sentence(1, r.choice((2, 22))) for _ in range(r.choice((1, 1, 2, 3, 5, 8))))
            if r.random() < 0.2:
                body = f"<b>{mark}{self.sentence(1, 5)}</b> " + body
            elif r.random() < 0.15:
                body = f"{mark}{self.sentence(1, 8)} <a href='/x'>{self.word()}</a> {body}"
            else:
                body = mark + body
            if k < 0.72:
                out.append(r.choice((f"<p>{body}</p>", f"<p>{body}</p>", f"<p>{body}", f"<p><b>{mark}{self.sentence(1, 30)}<br>", f"<div>{body}</div>")))
            elif k < 0.80:
                out.append(f"<h{r.choice('23')}>{mark}{self.sentence(1, 6)}</h2>")
            elif k < 0.87:
                out.append(r.choice(("<ul>", "<ol>")) + "".join(f"<li>{mark}{self.sentence(1, 9)}</li>" for _ in range(r.randint(1, 5))) + "</ul>")
            elif k < 0.91:
                out.append(f"<blockquote>{body}</blockquote>")
            elif k < 0.94:
                out.append("<table>" + "".join(f"<tr><td>{mark}{self.word()}</td><td>{mark}{r.randint(1, 999)}</td></tr>" for _ in range(r.randint(1, 3))) + "</table>")
            elif k < 0.96:
                out.append(f"<pre>{body}</pre>")
            else:
                out.append(self.chrome(r.choice(("ad", "side", "notice", "form"))))
        return "".join(out)

    def named(self, kind: str) -> str:
        return f' {self.r.choice(("class", "class", "id"))}="{self.r.choice(self.NAMES[kind])}"'

    def links(self, apart: str) -> str:
        return apart.join(f'<a href="/{i}">{self.r.choice(self.MENU) if self.r.random() < 0.6 else self.word()}</a>' for i in range(self.r.randint(2, 8)))

    def byline(self) -> str:
        tag = self.r.choice(("p", "div", "span", "p"))
        return f"<{tag}{self.named('meta') if self.r.random() < 0.7 else ''}>{self.saying('meta')}</{tag}>"

    def blog(self) -> str:
        """Nested divisions without elements that say what they are; title and byline stand inside the post."""
        r = self.r
        top = f"<div{self.named('head')}><h{r.choice('123')}>{self.word().capitalize()} {self.word()}</h1><p>{self.saying('head')}</p></div>"
        menu = f"<div{self.named('nav')}>{self.links(r.choice((' ', ' | ', '<br>')))}</div>" if r.random() < 0.5 else f"<ul{self.named('nav')}><li>" + self.links("</li><li>") + "</li></ul>"
        h = r.choice("112")
        title = f"<h{h}{' class=title' if r.random() < 0.3 else ''}>{self.MARK}{self.sentence(2, 12)}</h{h}>"
        body = re.sub(r"^(?:<header>)?<h1>.*?</h1>(?:</header>)?", "", self.main())
        about = [self.byline()] if r.random() < 0.8 else []
        post = "".join([title, *about] if r.random() < 0.8 else [*about, title]) + (f"<div{self.named('main')}>{body}</div>" if r.random() < 0.5 else body)
        tail = f"<p>{self.saying('meta')}</p>" if r.random() < 0.3 else ""
        rest = [self.chrome(k) for k in ("side", "comments", "form", "nav") if r.random() < 0.5]
        before, after = (rest[:1], rest[1:]) if r.random() < 0.5 else ([], rest)
        foot = f"<div{self.named('footer')}>{self.saying(r.choice(('footer', 'foot')))}</div>" if r.random() < 0.9 else ""
        return f"<div{self.named('wrap')}>" + top + menu + "".join(before) + f"<div{self.named('main')}>{post}{tail}</div>" + "".join(after) + foot + "</div>"

    def grid(self) -> str:
        """A page laid out by a table: a row for the name, a column of links, the text in a cell, a last row."""
        r = self.r
        inner = self.main() if r.random() < 0.8 else f"<font size=5><b>{self.MARK}{self.sentence(2, 9)}</b></font><br>{self.sentence(9, 30)}" + "".join(f"<p>{self.MARK}{self.sentence(8, 30)}" for _ in range(r.randint(1, 6)))
        top = f"<tr><td colspan=2><h{r.choice('123')}>{self.word().capitalize()} {self.word()}</h1></td></tr>" if r.random() < 0.6 else ""
        menu = f"<td width=150 valign=top>{self.links('<br>')}</td>" if r.random() < 0.6 else f"<td width=120><ul><li>{self.links('</li><li>')}</li></ul></td>"
        bar = f"<tr><td colspan=2>{self.links(' | ')}</td></tr>" if r.random() < 0.4 else ""
        cells = [menu, f"<td valign=top>{inner}</td>"] if r.random() < 0.8 else [f"<td valign=top>{inner}</td>", menu]
        foot = f"<tr><td colspan=2>{r.choice(('<center>', '<small>', '', '<font size=1>'))}{self.saying('foot')}</td></tr>" if r.random() < 0.7 else ""
        after = r.choice(("", f"<p>{self.saying('foot')}</p>", f"<hr>{self.saying('foot')}", f"<center>{self.saying('foot')}</center>"))
        return f"<table{r.choice((' width=100%', ' border=0', ''))}>" + top + bar + f"<tr>{''.join(cells)}</tr>" + foot + "</table>" + after

    def page(self) -> str:
        r = self.r
        kind = r.random()
        title = self.sentence(2, 10)
        body = self.blog() if kind < 0.2 else self.grid() if kind < 0.35 else self.sections()
        return f"<!DOCTYPE html><html><head><title>{title}</title><style>p{{}}</style></head><body>{body}</body></html>"

    def sections(self) -> str:
        """Chrome, the article in an element or a division of its own, chrome."""
        r = self.r
        kinds = ["nav"] * r.choice((0, 1, 1, 2)) + ["ad"] * r.choice((0, 1, 1)) + ["notice"] * r.choice((0, 0, 1)) + ["head"] * r.choice((0, 1))
        r.shuffle(kinds)
        body = "".join(map(self.chrome, kinds))
        if r.random() < 0.75:
            a, b = r.choice((("<article>", "</article>"), ("<main>", "</main>"), ("<main><article>", "</article></main>"), ('<article class="post">', "</article>")))
        else:
            a, b = f"<div{self.named('main')}>", "</div>"
        inner = self.main()
        if r.random() < 0.15:
            inner += self.chrome(r.choice(("comments", "side", "footer")))
        body += a + inner + b
        tail = [k for k in ("comments", "side", "ad", "form", "nav", "notice") if r.random() < 0.3] + ["footer"] * (r.random() < 0.85)
        return body + "".join(map(self.chrome, tail))


def labelled(seed: int) -> tuple[list[Block], np.ndarray]:
    """A generated page's blocks and which of them are main text."""
    page = blocks(Writer(seed).page())
    y = np.array([Writer.MARK in b.text for b in page], np.float32)
    for b in page:
        b.text = " ".join(b.text.replace(Writer.MARK, "").split()) or "."
    return page, y


@lru_cache(1)
def trained(pages: int = 1800) -> Labeller:
    """The labeller fitted to generated pages; the same each time."""
    made = [labelled(i) for i in range(pages)]
    return Labeller().fit([(inputs(p), y) for p, y in made if p])


def main_text(pages: list[str | None], labeller: Labeller) -> list[str]:
    found = [blocks(p) for p in pages]
    keep = labeller.keep([inputs(b) for b in found])
    return ["\n\n".join(b.text for b, k in zip(bs, ks) if k) for bs, ks in zip(found, keep)]


def extract(pages: DataFrame, labeller: Labeller | None = None) -> DataFrame:
    """(page_id, url, text, n_chars) of every row, from the whole html. One pass, no exchange.

    A null or empty page has the text '' and no characters; ids and urls may be null; rows that repeat repeat.
    """
    labeller = labeller or trained()
    out = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_chars", pa.int64())])

    def work(batches):
        for b in slices(batches, 64):
            texts = main_text(b.column(2).to_pylist(), labeller)
            yield batch(out, [b.column(0), b.column(1).cast(pa.string()), texts, [len(t) for t in texts]])

    return over_batches(pages.select(F.col("page_id").cast("bigint"), "url", "html"), work, "page_id bigint, url string, text string, n_chars bigint")
