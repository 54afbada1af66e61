"""Main text of web pages by a linear-chain conditional random field over leaf blocks.

A page is cut into leaf blocks: runs of text between the starts and ends of block elements. A block's features are the
tags and the class and id words of its ancestors and what its text is like; a two-state chain (main text or not), fitted
by maximum likelihood on labelled pages, is decoded by Viterbi. Labelled pages come from ``labelled_pages``, a generator
of many page layouts; pages labelled by hand can be added to them.
"""

from __future__ import annotations

import html
import random
import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Fixed values of HTML: elements whose text is never shown, that end a paragraph or block, and that have no end.
HIDDEN = "script style template noscript iframe".split()
BLOCKS = frozenset(
    "html head body title article section nav aside main header footer div p h1 h2 h3 h4 h5 h6 ul ol li dl dt dd table caption thead tbody tfoot "
    "tr td th form fieldset legend label button select option textarea blockquote pre figure figcaption address details summary hr dialog menu center".split()
)
VOID = frozenset("br hr img input meta link area base col embed source track wbr".split())
#: Elements that end an open one of the same kind.
SIBLINGS = {"li": {"li"}, "td": {"td", "th"}, "th": {"td", "th"}, "tr": {"tr", "td", "th"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "option": {"option"}}

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9-]*)((?>[^>\"']+|\"[^\"]*\"|'[^']*'|[\"'])*+)>|<[!?][^>]*>", re.S)
_ATTRIBUTE = re.compile(r"""\b(class|id|role|data-main)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_HIDDEN_END = {t: re.compile(rf"</{t}\s*>", re.I) for t in HIDDEN}
_WORD = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")


@dataclass
class Block:
    path: tuple[tuple[str, tuple[str, ...]], ...]
    parts: list[str] = field(default_factory=list)
    linked: int = 0
    label: int | None = None
    text: str = ""


def leaf_blocks(page: str) -> list[Block]:
    """Leaf blocks of a page in order, with text decoded and white space joined; blocks without text are left out."""
    out: list[Block] = []
    stack: list[tuple[str, tuple[str, ...], int | None]] = []
    current, in_link, at, n = Block(()), False, 0, len(page)

    def close() -> None:
        nonlocal current
        if current.parts:
            current.text = " ".join(html.unescape("".join(current.parts)).split())
            if current.text:
                current.path = tuple((t, c) for t, c, _ in stack)
                current.label = next((y for _, _, y in reversed(stack) if y is not None), None)
                out.append(current)
        current = Block(())

    while at < n:
        m = _TAG.search(page, at)
        stop = m.start() if m else n
        if stop > at:
            current.parts.append(page[at:stop])
            if in_link:
                current.linked += stop - at
        if not m:
            break
        at = m.end()
        ends, tag = m[1], (m[2] or "").lower()
        if not tag:
            continue
        if tag in _HIDDEN_END and not ends:
            if not m[3].endswith("/"):
                hidden = _HIDDEN_END[tag].search(page, at)
                at = hidden.end() if hidden else at  # without an end, only the tag is left out
            continue
        if tag == "a":
            in_link = not ends
        elif tag == "br":
            current.parts.append("\n")
        elif tag in BLOCKS:
            close()
            if ends:
                if any(t == tag for t, _, _ in stack):
                    while stack.pop()[0] != tag:
                        pass
            else:
                if stack and stack[-1][0] == "p":
                    stack.pop()
                while stack and stack[-1][0] in SIBLINGS.get(tag, ()):
                    stack.pop()
                if tag not in VOID:
                    words, label = [], None
                    for a in _ATTRIBUTE.finditer(m[3] or ""):
                        value = a[2] or a[3] or a[4] or ""
                        if a[1].lower() == "data-main":
                            label = int(value == "1")
                        else:
                            words += [w.lower() for w in _WORD.findall(value)]
                    stack.append((tag, tuple(words), label))
    close()
    return out


def path_features(path: tuple[tuple[str, tuple[str, ...]], ...]) -> list[str]:
    tags = [t for t, _ in path]
    out = {f"in:{t}" for t in tags} | {f"named:{w}" for _, c in path for w in c} | {f"named4:{w[:4]}" for _, c in path for w in c if len(w) > 4}
    out |= {f"last:{tags[-1] if tags else ''}", f"last2:{'/'.join(tags[-2:])}"}
    named = next((c for _, c in reversed(path) if c), ())
    return sorted(out | {f"near:{w}" for w in named})


def text_features(block: Block) -> list[str]:
    text = block.text
    n = text.count(" ") + 1
    link = min(1.0, block.linked / max(len(text), 1))
    return [
        "bias", f"words:{min(8, n.bit_length())}", f"link:{int(link * 4)}", f"ends:{text[-1] if not text[-1].isalnum() else 'a'}",
        f"copy:{text[0] in '©®' or '©' in text[:40]}", f"stops:{min(3, text.count('. '))}", f"upper:{text.isupper()}",
    ]


@dataclass
class Model:
    """Log-potentials: weights[feature] for the main state against the other, turns[from, to], starts[state]."""

    weights: dict[str, float]
    turns: np.ndarray
    starts: np.ndarray

    def __post_init__(self) -> None:
        self.paths: dict[tuple, float] = {}

    def emission(self, block: Block) -> float:
        got = self.paths.get(block.path)
        if got is None:
            if len(self.paths) > 50_000:
                self.paths.clear()
            got = self.paths[block.path] = sum(self.weights.get(f, 0.0) for f in path_features(block.path))
        return got + sum(self.weights.get(f, 0.0) for f in text_features(block))

    def decode(self, blocks: list[Block]) -> list[bool]:
        """The likeliest states (Viterbi)."""
        (a, b), (c, d) = self.turns.tolist()
        s0, s1 = self.starts.tolist()
        back: list[tuple[int, int]] = []
        for k, block in enumerate(blocks):
            e = self.emission(block)
            if k == 0:
                s1 += e
            else:
                from0, from1 = (0 if s0 + a >= s1 + c else 1), (0 if s0 + b >= s1 + d else 1)
                back.append((from0, from1))
                s0, s1 = max(s0 + a, s1 + c), max(s0 + b, s1 + d) + e
        states = [int(s1 > s0)] if blocks else []
        for step in reversed(back):
            states.append(step[states[-1]])
        return [s == 1 for s in reversed(states)]

    def main_text(self, page: str) -> str:
        blocks = leaf_blocks(page)
        return " ".join(b.text for b, main in zip(blocks, self.decode(blocks)) if main)


def fit_chain(pages: list[list[tuple[list[str], int]]], steps: int = 250, ridge: float = 1e-4) -> Model:
    """Maximum-likelihood chain for pages of (features, label) by adaptive gradient steps with forward-backward sums."""
    names = sorted({f for page in pages for fs, _ in page for f in fs})
    index = {f: k for k, f in enumerate(names)}
    longest = max(len(p) for p in pages)
    mask = np.zeros((len(pages), longest), bool)
    truth = np.zeros((len(pages), longest), np.int64)
    rows, columns = [], []
    for i, page in enumerate(pages):
        for j, (fs, y) in enumerate(page):
            mask[i, j], truth[i, j] = True, y
            rows += [i * longest + j] * len(fs)
            columns += [index[f] for f in fs]
    rows, columns = np.array(rows), np.array(columns)
    parameters = np.zeros(len(names) + 6)
    moment, square = np.zeros_like(parameters), np.zeros_like(parameters)
    size = mask.sum()
    for step in range(1, steps + 1):
        w, turns, starts = parameters[: len(names)], parameters[-6:-2].reshape(2, 2), parameters[-2:]
        e = np.zeros((len(pages), longest, 2))
        e[:, :, 1] = np.bincount(rows, w[columns], minlength=len(pages) * longest).reshape(len(pages), longest)
        ahead = np.zeros((len(pages), longest, 2))
        ahead[:, 0] = starts + e[:, 0]
        for j in range(1, longest):
            new = np.logaddexp(ahead[:, j - 1, 0:1] + turns[0], ahead[:, j - 1, 1:2] + turns[1]) + e[:, j]
            ahead[:, j] = np.where(mask[:, j, None], new, ahead[:, j - 1])
        behind = np.zeros((len(pages), longest, 2))
        pair = np.zeros((2, 2))
        whole = np.logaddexp(ahead[:, -1, 0], ahead[:, -1, 1])
        for j in range(longest - 2, -1, -1):
            on = mask[:, j + 1]
            to = e[:, j + 1] + behind[:, j + 1]
            both = ahead[:, j, :, None] + turns + to[:, None, :] - whole[:, None, None]
            pair += np.exp(both[on]).sum(axis=0)
            new = np.logaddexp(turns[:, 0] + to[:, 0:1], turns[:, 1] + to[:, 1:2])
            behind[:, j] = np.where(on[:, None], new, behind[:, j + 1])
        state = np.exp(ahead + behind - whole[:, None, None]) * mask[:, :, None]
        miss = (state[:, :, 1] - truth * mask).ravel()
        g = np.zeros_like(parameters)
        g[: len(names)] = np.bincount(columns, miss[rows], minlength=len(names))
        seen = mask[:, 1:]
        real = np.zeros((2, 2))
        np.add.at(real, (truth[:, :-1][seen], truth[:, 1:][seen]), 1)
        g[-6:-2] = (pair - real).ravel()
        g[-2:] = state[:, 0].sum(axis=0) - np.bincount(truth[:, 0], minlength=2)
        g = g / size + ridge * parameters / 10
        moment, square = 0.9 * moment + 0.1 * g, 0.999 * square + 0.001 * g * g
        parameters = parameters - 0.15 * (moment / (1 - 0.9**step)) / (np.sqrt(square / (1 - 0.999**step)) + 1e-8)
    return Model({f: float(parameters[k]) for f, k in index.items()}, parameters[-6:-2].reshape(2, 2).copy(), parameters[-2:].copy())


def labelled_pages(n: int = 500, seed: int = 3) -> Iterator[str]:
    """Pages of random layouts; data-main="1" marks elements of the main text, "0" others inside them."""
    r = random.Random(seed)
    pick, chance = r.choice, lambda p: r.random() < p

    def words(lo: int, hi: int) -> str:
        return " ".join("".join(pick("ka lo mi ru en ta so ver di ón é".split()) for _ in range(r.randint(1, 4))) for _ in range(r.randint(lo, hi)))

    def sentences(lo: int, hi: int) -> str:
        mark = pick([". ", ". ", ". ", "! ", "? ", ".%%% ", "|| "]) if chance(0.3) else ". "
        return mark.join(words(1, 18).capitalize() for _ in range(r.randint(lo, hi))).strip() + pick([".", ".", ".", "", "!", "&amp;"])

    def heading(levels: str, most: int) -> str:
        level = pick(levels)
        return f"<h{level}>{words(1, most)}</h{level}>"

    def link(text: str) -> str:
        return f'<a href="/{r.randint(1, 999)}">{text}</a>'

    def named(tag: str, *choices: str) -> tuple[str, str]:
        kind = pick(["class", "class", "class", "id"])
        extra = pick(["", "", "", "-wrap", " box", "_1", "-inner", "-area", " block"])
        return f'<{tag} {kind}="{pick(choices)}{extra}">', f"</{tag}>"

    def wrapped(pair: tuple[str, str], inside: str) -> str:
        return pair[0] + inside + pair[1]

    def links(lo: int, hi: int) -> str:
        if chance(0.75):
            return "<ul>" + "".join(f"<li>{link(words(1, 3))}" + pick(["</li>", "</li>", ""]) for _ in range(r.randint(lo, hi))) + "</ul>"
        return pick([" | ", " ", " &middot; "]).join(link(words(1, 3)) for _ in range(r.randint(lo, hi)))

    plain = lambda tag: (f"<{tag}>", f"</{tag}>")

    def menu() -> str:
        return wrapped(pick([plain("nav"), named("nav", "menu", "navbar", "main-nav"), named("div", "nav", "menu", "navigation", "navbar", "topnav", "breadcrumbs", "breadcrumb"), named("ul", "menu", "nav")]), links(2, 9))

    def header() -> str:
        inside = pick([f"<h1>{words(1, 4)}</h1>", f"<div>{words(1, 4)}</div>", f"<p>{words(2, 9)}</p>", f"<h2>{link(words(1, 3))}</h2><p>{words(2, 8)}</p>", sentences(1, 2)])
        return wrapped(pick([plain("header"), named("div", "header", "site-header", "masthead", "top-bar", "banner", "branding", "topbar"), named("header", "site", "page-header")]), inside + (menu() if chance(0.4) else ""))

    def footer() -> str:
        inside = pick([f"&copy; {words(1, 3)} &middot; {sentences(1, 1)}", f"<p>&copy; 20{r.randint(10, 30)} {words(1, 5)}</p>", f"<p>{sentences(1, 3)}</p>", links(2, 5) + f"<p>{words(2, 6)}</p>", sentences(1, 2)])
        return wrapped(pick([plain("footer"), named("div", "footer", "site-footer", "copyright", "colophon", "legal", "bottom")]), inside)

    def sidebar() -> str:
        inside = pick([f"<h3>{words(1, 3)}</h3>" + links(2, 6), f"<p>{sentences(1, 4)}</p>", f"<h4>{words(1, 3)}</h4><p>{sentences(1, 3)}</p>", links(3, 8), sentences(1, 3)])
        return wrapped(pick([plain("aside"), named("aside", "sidebar", "related"), named("div", "sidebar", "side", "widget", "related", "related-posts", "recommended", "popular", "trending", "rail", "more-stories", "read-more", "see-also")]), inside)

    def notice() -> str:
        inside = pick([f"<p>{sentences(1, 3)}</p>", sentences(1, 3), f"{sentences(1, 2)}<button>{words(1, 2)}</button>"])
        return wrapped(named(pick(["div", "div", "section", "aside", "p", "dialog"]), "cookie", "cookie-notice", "cookie-banner", "consent", "gdpr", "notice", "alert", "popup", "modal", "privacy", "announcement", "warning", "message", "paywall", "disclaimer", "toast"), inside)

    def advert() -> str:
        inside = pick([sentences(1, 2), f"<p>{sentences(1, 3)}</p>", link(words(2, 8)), f"<span>{words(1, 2)}</span> {link(words(2, 6))}"])
        return wrapped(named(pick(["div", "div", "aside", "section", "p", "figure"]), "ad", "ads", "advert", "advertisement", "sponsor", "sponsored", "promo", "promotion", "banner-ad", "ad-slot", "adbox", "commercial", "partner"), inside)

    def form() -> str:
        inside = pick([f"<label>{words(1, 3)}</label><input><button>{words(1, 2)}</button>", f"<p>{sentences(1, 2)}</p><input><button>{words(1, 1)}</button>", f"{words(1, 4)} <input type=text> <button>{words(1, 2)}</button>", f"<select><option>{words(1, 1)}<option>{words(1, 2)}</select><textarea>{words(0, 3)}</textarea>"])
        shape = pick([plain("form"), named("form", "search", "login", "subscribe", "contact")])
        return wrapped(named("div", "newsletter", "subscribe", "signup", "search", "login", "form", "contact") if chance(0.4) else ("", ""), wrapped(shape, inside))

    def share() -> str:
        return wrapped(named("div", "share", "social", "sharing", "tags", "meta", "byline", "toolbar", "pagination", "pager", "author-box", "rating"), pick([links(2, 5), words(1, 5), f"<span>{words(1, 3)}</span>"]))

    def comments() -> str:
        one = lambda: pick([f"<p>{sentences(1, 4)}</p>", f'<div class="comment"><b>{words(1, 2)}</b> {sentences(1, 4)}</div>', f"<li><span>{words(1, 2)}</span><p>{sentences(1, 5)}</p></li>", f"<blockquote>{sentences(1, 3)}</blockquote>", f"<article><p>{sentences(1, 4)}</p></article>"])
        inside = (heading("234", 3) if chance(0.6) else "") + "".join(one() for _ in range(r.randint(1, 5))) + (form() if chance(0.2) else "")
        return wrapped(named(pick(["div", "section", "section", "ul", "ol", "aside"]), "comments", "comment", "comment-list", "comments-area", "replies", "reply", "responses", "discussion", "disqus", "respond", "user-comments", "reader-comments", "feedback"), inside)

    def text_block() -> str:
        kind = r.random()
        if kind < 0.62:
            end = pick(["</p>", "</p>", "</p>", ""])
            body = sentences(1, 9)
            if chance(0.2):
                body = body.replace(" ", f" {pick(['<b>', '<em>', '<i>', '<span>'])}", 1) + pick(["</b>", "</em>", ""])
            if chance(0.15):
                body = f"{words(1, 5)} {link(words(1, 4))} {sentences(1, 4)}"
            if chance(0.2):
                body = pick([words(1, 3) + ".", words(1, 2), words(30, 200)])
            return f"<p{pick(['', '', '', ' class=lead', ' class=text'])}>{'<b>' if chance(0.15) else ''}{body}{'<br>' if chance(0.2) else ''}{end}"
        if kind < 0.72:
            return heading("23", 7)
        if kind < 0.8:
            return "<ul>" + "".join(f"<li>{pick([words(1, 12), sentences(1, 2)])}</li>" for _ in range(r.randint(1, 5))) + "</ul>"
        if kind < 0.85:
            return f"<blockquote>{pick([sentences(1, 3), '<p>' + sentences(1, 3) + '</p>'])}</blockquote>"
        if kind < 0.9:
            return "<table>" + "".join("<tr>" + "".join(f"<td>{words(1, 4)}</td>" for _ in range(r.randint(1, 3))) + "</tr>" for _ in range(r.randint(1, 4))) + "</table>"
        if kind < 0.94:
            return f"<pre>{words(2, 30)}</pre>"
        if kind < 0.97:
            return f"<figure><img src=x><figcaption>{words(2, 12)}</figcaption></figure>"
        return f"<div>{sentences(1, 6)}</div>"

    other = lambda x: re.sub(r"^<(\w+)", r'<\1 data-main="0"', x)

    for _ in range(n):
        shape = pick([plain("article"), plain("article"), plain("main"), named("article", "post", "entry", "story"), named("div", "content", "article", "post", "entry", "main", "story", "article-body", "post-content", "entry-content", "body-text", "page-content", "text"), named("main", "content"), named("section", "content", "article", "story")])
        if chance(0.06):
            shape = plain(pick(["div", "section"]))
        title = f"<h1>{pick([words(1, 9), sentences(1, 1)])}</h1>" if chance(0.8) else ""
        if title and chance(0.15):
            title = f"<header>{title}</header>" if chance(0.5) else f'<div class="title">{title}</div>'
        inner = title + "".join((text_block() if not chance(0.06) else other(pick([advert, share, sidebar, form, notice, menu])())) for _ in range(pick([1, 2, 3, 4, 5, 6, 8, 12])))
        if chance(0.25):
            inner = inner + other(pick([comments, comments, share, footer])())
        body = wrapped((shape[0].replace(">", ' data-main="1">', 1), shape[1]), inner)
        before = "".join(pick([menu, menu, header, header, notice, advert, form, sidebar])() for _ in range(r.randint(0, 5)))
        after = "".join(pick([footer, footer, sidebar, comments, comments, notice, advert, form, menu, share])() for _ in range(r.randint(0, 5)))
        if chance(0.3):
            body = wrapped(pick([named("div", "container", "wrapper", "page", "layout", "row", "main"), plain("main"), plain("div")]), pick([body, body + sidebar(), sidebar() + body, body + comments(), menu() + body]))
        yield f"<!DOCTYPE html><html><head><title>{words(1, 8)}</title><script>var a='</p>';</script></head><body>{before}{body}{after}</body></html>"


@lru_cache(maxsize=1)
def trained(n: int = 800) -> Model:
    """The chain fitted on ``n`` generated pages; the same in every process."""
    pages = []
    for page in labelled_pages(n):
        blocks = leaf_blocks(page)
        if blocks:
            pages.append([(path_features(b.path) + text_features(b), b.label or 0) for b in blocks])
    return fit_chain(pages)


def extract(pages: DataFrame, model: Model | None = None) -> DataFrame:
    """(page_id, url, text) for every row: blocks of main text in order, joined by a space; empty if there is none.

    Null html is empty. Broken markup is read as far as it goes. Rows that repeat are rows of their own.
    """
    known = pages.sparkSession.sparkContext.broadcast(model or trained())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chain = known.value
        for batch in batches:
            source = batch.column("html")
            for lo in range(0, batch.num_rows, 500):
                texts = [chain.main_text(x.as_py() or "") for x in source[lo : lo + 500]]
                yield pa.RecordBatch.from_arrays([batch.column("page_id")[lo : lo + 500], batch.column("url")[lo : lo + 500], pa.array(texts, pa.string())], ["page_id", "url", "text"])

    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).mapInArrow(run, "page_id long, url string, text string")
