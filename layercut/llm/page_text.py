"""Operator 4: main text of web pages by a linear-chain conditional random field over the leaf blocks of the page tree.

A page becomes its leaf blocks in page order: runs of text between block-level tags, each with its ancestors. Features of a block are
its ancestor tags, the words of their class and id attributes, its own tag, its length, the share of its text inside links and
its punctuation. The field has two states, article or not; its weights are learned by gradient ascent on the conditional
likelihood of labelled pages and the best state sequence is found by Viterbi decoding. The labelled pages are made by rule
(labelled_pages): layouts drawn with a fixed seed from the usual containers for menus, headers, adverts, notices, articles,
sidebars, forms, comments and footers, in which every block's state is known.

Defined results: null, empty and tag-only pages have an empty text; markup that is never closed or cut off is read as far as it goes;
repeated rows are extracted alike; text outside any tag is a block without ancestors; an empty table gives an empty result.
"""

from __future__ import annotations

import html as entities
import random
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import table

# HTML's void elements, elements whose text is not shown, and elements that stand inside a line.
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
HIDDEN = set("script style noscript template title textarea select svg iframe object".split())
INLINE = set("a abbr b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
CLOSED_BY_SAME = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
ENDS_P = set("address article aside blockquote div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())
#: A comment (to the page's end if it is not closed), a declaration, or the start of a tag.
_OPEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*+>?|<(/?)([a-zA-Z][^\s/>]*+)", re.S)
#: What follows a tag's name up to its end: quotes count only where a value begins, and nothing is read twice.
_INSIDE = re.compile(r"""(?:[^>=]++|=\s*+(?:"[^"]*+"|'[^']*+'|))*+""")
_ATTRIBUTE = re.compile(r"""([^\s"'>/=][^\s>/=]*+)(?:\s*+=\s*+(?:"([^"]*+)"|'([^']*+)'|([^\s>]*+)))?+""")
_SHUT = re.compile(r"""(?:\A|[\s"'])/\s*\Z""")
_SPLIT = re.compile(r"[^a-z0-9]+")
_ENDS = {tag: re.compile(rf"</{tag}\s*+>", re.I) for tag in HIDDEN}


@dataclass
class Block:
    """text, own tag, tags and names of its ancestors, whether any ancestor is named, and how much of the text stands in links."""

    text: str
    own: str
    tags: frozenset[str]
    names: frozenset[str]
    named: bool
    linked: int


def _names(inside: str, wanted: frozenset[str] | None) -> tuple[frozenset[str], bool]:
    """Words of the class, id and role attributes (those wanted), and whether there are any."""
    found = set()
    for name, *value in _ATTRIBUTE.findall(inside):
        if name.lower() in ("class", "id", "role"):
            found |= {w for w in _SPLIT.split("".join(value).lower()) if w}
    return frozenset(found if wanted is None else found & wanted), bool(found)


def leaf_blocks(page: str | None, wanted: frozenset[str] | None = None) -> list[Block]:
    """Blocks in page order; texts are decoded, with single blanks. wanted: the names to keep, all by default. Time is linear in the page."""
    page = page or ""
    out: list[Block] = []
    stack: list[tuple[str, frozenset[str], frozenset[str], bool]] = [("-", frozenset(), frozenset(), False)]  # tag, and of it and its ancestors: tags, names, named
    open_: dict[str, int] = {}
    run: list[str] = []
    linked = anchors = 0

    def flush() -> None:
        nonlocal linked
        if run:
            text = " ".join(entities.unescape("".join(run)).split())
            if text:
                own, tags, names, named = stack[-1]
                out.append(Block(text, own, tags, names, named, min(linked, len(text))))
            run.clear()
        linked = 0

    def add(raw: str) -> None:
        nonlocal linked
        if raw:
            run.append(raw)
            if anchors:
                linked += len(raw)

    def pop() -> None:
        open_[stack.pop()[0]] -= 1

    at = 0
    while m := _OPEN.search(page, at):
        add(page[at : m.start()])
        at = m.end()
        if not m[2]:
            continue
        inside = _INSIDE.match(page, at)
        at = inside.end() + 1
        if at > len(page):  # a tag that the end of the page cuts off
            break
        tag = m[2].lower()
        if tag in HIDDEN:
            if not m[1] and not _SHUT.search(inside[0]):
                end = _ENDS[tag].search(page, at)
                at = end.end() if end else len(page)
            continue
        if tag in INLINE:
            if tag == "br":
                run.append(" ")
            elif tag == "a":
                anchors = 0 if m[1] else 1
            continue
        flush()
        anchors = 0
        if m[1]:
            if open_.get(tag):
                while stack[-1][0] != tag:
                    pop()
                pop()
            continue
        if tag in ENDS_P and stack[-1][0] == "p":
            pop()
        while stack[-1][0] in CLOSED_BY_SAME.get(tag, ()):
            pop()
        if tag not in VOID and not _SHUT.search(inside[0]):
            _, tags, names, named = stack[-1]
            own, any_ = _names(inside[0], wanted) if "=" in inside[0] else (frozenset(), False)
            stack.append((tag, tags if tag in tags else tags | {tag}, names if own <= names else names | own, named or any_))
            open_[tag] = open_.get(tag, 0) + 1
    else:
        add(page[at:])
    flush()
    return out


def features(block: Block) -> set[str]:
    n, share = len(block.text.split()), block.linked / max(1, len(block.text))
    out = {"bias", f"own {block.own}", *(f"in {t}" for t in block.tags), *(f"name {w}" for w in block.names)}
    out.add(f"words {0 if n < 3 else 1 if n < 8 else 2 if n < 20 else 3}")
    out.add(f"links {0 if share == 0 else 1 if share < 0.5 else 2}")
    if block.text[-1:] in ".!?\"":
        out.add("stop")
    if "©" in block.text:
        out.add("copyright")
    if not any(t in block.tags for t in ("article", "main", "nav", "aside", "footer", "header", "form")) and not block.named:
        out.add("bare")
    return out


def labelled_pages(count: int = 400, seed: int = 4) -> Iterator[tuple[str, list[int]]]:
    """Pages made by rule, with the state (1: article) of each of their leaf blocks."""
    draw = random.Random(seed)
    word = lambda: "".join(draw.choice("aeiournstlmdhcg") for _ in range(draw.randint(2, 9)))
    phrase = lambda a, b: " ".join(word() for _ in range(draw.randint(a, b)))
    sentence = lambda: phrase(1, 25).capitalize() + draw.choice([".", ".", ".", "!", "?"])
    prose = lambda: " ".join(sentence() for _ in range(draw.choice([1, 1, 2, 4])))

    for _ in range(count):
        body: list[str] = []
        state: list[int] = []

        def put(tag: str, text: str, kind: int, body: list = body, state: list = state) -> None:
            body.append(f"<{tag}>{text}</{tag}>")
            state.append(kind)

        def box(tag: str, names: list[str], fill, body: list = body) -> None:
            name = draw.choice([*names, ""]) if tag != "div" else draw.choice(names)
            body.append(f"<{tag}" + (f' {draw.choice(["class", "class", "id"])}="{name}">' if name else ">"))
            fill()
            body.append(f"</{tag}>")

        def links(n: int) -> None:
            body.append("<ul>")
            for _ in range(n):
                put("li", f'<a href="/{word()}">{phrase(1, 5)}</a>', 0)
            body.append("</ul>")

        def advert() -> None:
            def fill() -> None:
                if draw.random() < 0.5:
                    body.append(prose())
                    state.append(0)
                else:
                    put("p", prose(), 0)

            box(draw.choice(["div", "div", "aside"]), ["ad", "ads", "advert", "banner", "sponsored", "promo", "advertisement"], fill)

        def notice() -> None:
            box(draw.choice(["div", "section"]), ["cookie-notice", "cookie", "consent", "notice", "gdpr", "popup", "alert"], lambda: put("p", prose(), 0))

        def form() -> None:
            body.append("<form>")
            put("p", f"<label>{phrase(1, 3)}</label> <input name='q'>", 0)
            put("button", word(), 0)
            body.append("</form>")

        def story() -> None:
            headed, count = draw.random() < 0.6, draw.choice([1, 1, 2, 2, *range(3, 13)])
            if headed:
                put(draw.choice(["h1", "h1", "h1", "h2"]), phrase(2, 10), 1)
            elif draw.random() < 0.1:
                body.append(prose())
                state.append(1)
                count -= 1
            for k in range(count):
                x = draw.random() if headed or k else 0.0
                if x < 0.8:
                    put("p", f"<b>{prose()}" if draw.random() < 0.1 else prose(), 1)
                elif x < 0.87:
                    put(draw.choice(["h2", "h3"]), phrase(1, 6), 1)
                elif x < 0.93:
                    body.append("<ul>")
                    for _ in range(draw.randint(1, 4)):
                        put("li", phrase(1, 12), 1)
                    body.append("</ul>")
                else:
                    put(draw.choice(["blockquote", "pre"]), prose(), 1)
                if draw.random() < 0.05:
                    advert()

        def remarks() -> None:
            put(draw.choice(["h2", "h3"]), phrase(1, 3), 0)
            for _ in range(draw.randint(1, 5)):
                if draw.random() < 0.5:
                    box("div", ["comment", "reply", "comment-body"], lambda: put("p", prose(), 0))
                else:
                    put("p", prose(), 0)

        alone = draw.random() < 0.25
        around = lambda chance, alone=alone: not alone and draw.random() < chance
        if around(0.3):
            notice()
        if around(0.4):
            box(draw.choice(["header", "div"]), ["header", "masthead", "top", "site-header"], lambda: put("p", phrase(1, 8), 0))
        if around(0.9):
            box(draw.choice(["nav", "nav", "div"]), ["menu", "nav", "navigation", "navbar", "breadcrumb"], lambda: links(draw.randint(2, 8)))
        if around(0.5):
            advert()
        if around(0.2):
            form()
        kind = draw.choice(["article", "article", "article", "main", "div", "section", "bare div", "body"])
        if kind == "body":
            story()
        elif kind == "bare div":
            body.append("<div>")
            story()
            body.append("</div>")
        else:
            box(kind, ["content", "article", "post", "entry", "story", "main", "article-body", "entry-content"], story)
        if around(0.4):
            box(draw.choice(["aside", "div"]), ["sidebar", "related", "widget", "aside", "share"], lambda: (put("h3", phrase(1, 3), 0), links(draw.randint(1, 5)), put("p", prose(), 0)))
        if around(0.4):
            box(draw.choice(["section", "div"]), ["comments", "comment-list", "discussion", "responses"], remarks)
        if around(0.3):
            form()
        if around(0.2):
            notice()
        if around(0.9):
            copyright_ = draw.choice(["&copy; ", "&copy; ", ""])
            box(draw.choice(["footer", "footer", "div"]), ["footer", "site-footer", "bottom", "legal"], lambda: (body.append(copyright_ + prose()), state.append(0)))
        yield f"<html><head><title>{phrase(2, 6)}</title></head><body>{''.join(body)}</body></html>", state


@dataclass
class Field:
    """Weights of the chain: emit[feature] for the article state against the other, step[a, b] from state a to b."""

    emit: dict[str, float]
    start: np.ndarray
    step: np.ndarray

    def names(self) -> frozenset[str]:
        """The names that have weights."""
        return frozenset(f[5:] for f in self.emit if f.startswith("name "))

    def states(self, blocks: list[Block]) -> list[int]:
        """Viterbi decoding."""
        if not blocks:
            return []
        best, back = None, []
        for b in blocks:
            e = sum(self.emit.get(f, 0.0) for f in features(b))
            if best is None:
                best = [float(self.start[0]), float(self.start[1]) + e]
                continue
            came, new = [], []
            for s in (0, 1):
                a, c = best[0] + self.step[0, s], best[1] + self.step[1, s]
                came.append(int(c > a))
                new.append(max(a, c) + e * s)
            best = new
            back.append(came)
        s = int(best[1] > best[0])
        out = [s]
        for came in reversed(back):
            s = came[s]
            out.append(s)
        return out[::-1]

    def text(self, page: str | None) -> str:
        blocks = leaf_blocks(page, self.names())
        return "\n\n".join(b.text for b, s in zip(blocks, self.states(blocks), strict=True) if s)


def train(pages: list[tuple[str, list[int]]], rounds: int = 120, rate: float = 0.15, ridge: float = 1e-3) -> Field:
    """Gradient ascent (Adam) on the conditional log-likelihood, by forward and backward sums over all pages at once."""
    rows = [([features(b) for b in leaf_blocks(p)], s) for p, s in pages]
    rows = [(f, s) for f, s in rows if f and len(f) == len(s)]
    index = {f: k for k, f in enumerate(sorted({f for fs, _ in rows for b in fs for f in b}))}
    longest = max(len(s) for _, s in rows)
    x = np.zeros((len(rows), longest, len(index)), dtype=np.float32)
    y, live = np.zeros((len(rows), longest), dtype=int), np.zeros((len(rows), longest), dtype=bool)
    for i, (fs, s) in enumerate(rows):
        y[i, : len(s)], live[i, : len(s)] = s, True
        for t, b in enumerate(fs):
            x[i, t, [index[f] for f in b]] = 1
    flat = x.reshape(-1, len(index))
    theta = np.zeros(len(index) + 6)
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    pairs = live[:, 1:]
    seen = np.zeros((2, 2))
    np.add.at(seen, (y[:, :-1][pairs], y[:, 1:][pairs]), 1)
    for k in range(1, rounds + 1):
        w, start, step = theta[:-6], theta[-6:-4], theta[-4:].reshape(2, 2)
        e = np.zeros((len(rows), longest, 2))
        e[..., 1] = (flat @ w.astype(np.float32)).reshape(len(rows), longest)
        fwd, bwd = np.zeros_like(e), np.zeros_like(e)
        fwd[:, 0] = start + e[:, 0]
        for t in range(1, longest):
            fwd[:, t] = np.where(live[:, t, None], np.logaddexp.reduce(fwd[:, t - 1, :, None] + step, axis=1) + e[:, t], fwd[:, t - 1])
        for t in range(longest - 2, -1, -1):
            bwd[:, t] = np.where(live[:, t + 1, None], np.logaddexp.reduce(step + (e[:, t + 1] + bwd[:, t + 1])[:, None, :], axis=2), bwd[:, t + 1])
        z = np.logaddexp.reduce(fwd[:, -1], axis=1)
        p = np.exp(fwd + bwd - z[:, None, None])
        both = np.exp(fwd[:, :-1, :, None] + step + (e + bwd)[:, 1:, None, :] - z[:, None, None, None]) * pairs[..., None, None]
        g = np.concatenate([((y - p[..., 1]) * live).reshape(-1).astype(np.float32) @ flat, np.bincount(y[:, 0], minlength=2) - p[:, 0].sum(axis=0), (seen - both.sum(axis=(0, 1))).reshape(-1)])
        g = g / len(rows) - ridge * theta
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        theta = theta + rate * (m / (1 - 0.9**k)) / (np.sqrt(v / (1 - 0.999**k)) + 1e-8)
    return Field({f: float(theta[i]) for f, i in index.items()}, theta[-6:-4].copy(), theta[-4:].reshape(2, 2).copy())


def extract(pages: DataFrame, field: Field) -> DataFrame:
    """pages with page_text."""
    shipped = pages.sparkSession.sparkContext.broadcast(field)  # a few hundred weights

    @F.pandas_udf("string")
    def run(html: pd.Series) -> pd.Series:
        return pd.Series([shipped.value.text(h) for h in html], dtype=object)

    return pages.withColumn("page_text", run(F.col("html").cast("string")))


def op4_page_text(spark, sf_dir: str) -> DataFrame:
    out = extract(table(spark, sf_dir, "pages").select("page_id", "url", "html"), train(list(labelled_pages())))
    return out.select("page_id", "url", F.col("page_text").alias("text"), F.length("page_text").cast("long").alias("n_chars"))
