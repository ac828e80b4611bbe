"""Main text of web pages: boosted trees over DOM nodes, decoded so that no choice contradicts.

Every block element gets features of its tag, attribute words (its own and those it inherits),
depth, place among siblings, subtree text, link and tag density, and punctuation. Gradient-boosted
trees, trained here on generated pages of many layouts, give each node the odds of being main
text. Decoding keeps a subtree or drops it whole: a node can only be kept if its parent is, and
the choice of largest total evidence is found bottom-up.

Defined results: a null or empty page and a page without main text give an empty text; broken
and unclosed markup is repaired as far as `html_tree` goes, never refused; script, style and form
controls hold no text, nor do drawings, formulas and fallback elements once they are closed; very
long pages are processed whole, in time that grows with their length; repeated rows repeat; extra
columns are not read.
"""

from __future__ import annotations

import random
import zlib
from collections.abc import Callable
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import boosting
from .common import map_texts
from .html_tree import Page

_TAG_GROUPS = (
    {"nav", "menu"}, {"header"}, {"footer"}, {"aside", "dialog"}, {"article"}, {"main"}, {"section"}, {"div"}, {"p"}, {"h1", "h2", "h3", "h4", "h5", "h6", "hgroup"},
    {"ul", "ol", "dl"}, {"li", "dt", "dd"}, {"table", "tbody", "thead", "tfoot", "tr", "td", "th", "caption"}, {"form", "fieldset", "button", "legend", "output", "progress", "meter", "datalist", "optgroup", "option"},
    {"figure", "figcaption", "details", "summary"}, {"blockquote", "pre", "address"}, {"head"}, {"body", "html", "#root"},
)
_GROUP = {t: k for k, g in enumerate(_TAG_GROUPS) for t in g}
#: Words of class, id and role attributes by what they usually mark.
_WORD_GROUPS = (
    {"ad", "ads", "adv", "advert", "adverts", "advertisement", "advertising", "sponsor", "sponsored", "promo", "promotion", "promoted", "banner", "dfp", "adsense", "commercial", "affiliate"},
    {"nav", "navbar", "navigation", "menu", "breadcrumb", "breadcrumbs", "toc", "pagination", "pager", "tabs", "toolbar", "skip", "sitemap"},
    {"header", "masthead", "topbar", "head", "logo", "branding"},
    {"footer", "foot", "bottom", "copyright", "legal", "colophon", "contentinfo"},
    {"sidebar", "side", "aside", "widget", "rail", "complementary", "related", "recommended", "recommend", "popular", "trending", "more", "teaser", "links"},
    {"comment", "comments", "reply", "replies", "respond", "disqus", "discussion", "thread", "commentlist", "reader", "feedback", "review", "reviews"},
    {"cookie", "cookies", "consent", "gdpr", "notice", "notification", "alert", "popup", "modal", "overlay", "dialog", "message", "warning", "privacy", "toast", "paywall", "disclaimer"},
    {"share", "sharing", "social", "follow", "newsletter", "subscribe", "subscription", "signup", "login", "signin", "search", "form", "register", "cta", "contact"},
    {"content", "article", "post", "entry", "story", "text", "body", "main", "prose", "page", "blog", "single", "copy", "paragraph"},
    {"hidden", "print", "screen", "sr", "offscreen", "visually", "meta", "byline", "author", "date", "tags", "tag", "category"},
)
_N_TAGS, _N_WORDS = len(_TAG_GROUPS), len(_WORD_GROUPS)
_WORD_OF = {w: k for k, g in enumerate(_WORD_GROUPS) for w in g}
#: Other words of the attributes are told apart by hash, in so many features.
_N_HASHED = 16
#: Nodes whose features are laid out at once, about.
_NODES = 8192
WIDTH = _N_TAGS + 2 * _N_WORDS + _N_HASHED + _N_TAGS + 18


@lru_cache(maxsize=50_000)
def _word_bit(word: str) -> int:
    """A known word's group, or the hash of another one above all groups."""
    known = _WORD_OF.get(word)
    return 1 << known if known is not None else 1 << (_N_WORDS + zlib.crc32(word.encode("utf-8", "surrogatepass")) % _N_HASHED)


def features(page: Page) -> tuple[Callable[[int, int], np.ndarray], np.ndarray, np.ndarray]:
    """(features of the nodes from one place to another, characters of each one's own text, of its subtree)."""
    tag, parent = page.tag, page.parent
    n = len(tag)
    own, linked, marks, runs = [0] * n, [0] * n, [0] * n, [0] * n
    hidden = page.hidden()
    for node, text, link in page.pieces:
        if text is not None and node not in hidden:
            size = len(text) if not text.isspace() else 0
            if size:
                own[node] += size
                runs[node] += 1
                if link:
                    linked[node] += size
                elif size > 20:
                    marks[node] += text.count(".") + text.count(",") - text.count("&") // 4
    group = [_GROUP.get(t, 7) for t in tag]
    mask, up, depth, children, place = [0] * n, [0] * n, [0] * n, [0] * n, [0] * n
    tags_above = [0] * n
    for v in range(1, n):
        p = parent[v]
        m = 0
        for w in page.words[v]:
            m |= _word_bit(w)
        mask[v] = m
        up[v] = up[p] | mask[p]
        tags_above[v] = tags_above[p] | (1 << group[p])
        depth[v] = depth[p] + 1
        place[v] = children[p]
        children[p] += 1
    sub, sub_link, sub_marks, below, paragraphs, p_chars = own[:], linked[:], marks[:], [0] * n, [0] * n, [0] * n
    for v in range(n - 1, 0, -1):
        p = parent[v]
        if tag[v] == "p":
            paragraphs[v] += 1
            p_chars[v] += own[v]
        sub[p] += sub[v]
        sub_link[p] += sub_link[v]
        sub_marks[p] += sub_marks[v]
        below[p] += below[v] + 1
        paragraphs[p] += paragraphs[v]
        p_chars[p] += p_chars[v]
    a = lambda v: np.array(v, dtype=np.float64)
    own_a, sub_a, parent_a = a(own), a(sub), np.array([max(0, p) for p in parent])
    siblings = a(children)[parent_a]
    total = max(1.0, float(sub[0]))
    rest = [
        a(depth), np.log1p(own_a), np.log1p(sub_a), sub_a / total, a(sub_link) / np.maximum(1, sub_a), a(below) / np.maximum(20, sub_a) * 100, np.log1p(a(below)),
        a(place), a(place) / np.maximum(1, siblings), siblings, a(sub_marks) / np.maximum(30, sub_a) * 100, np.log1p(a(paragraphs)), a(p_chars) / np.maximum(1, sub_a),
        sub_a / np.maximum(1, sub_a[parent_a]), np.log1p(sub_a[parent_a]) - np.log1p(sub_a), a(paragraphs)[parent_a], np.cumsum(own_a) / total, a([len(w) for w in page.words]),
    ]
    group_a, mask_a, up_a, above_a = (np.array(v, dtype=np.int64) for v in (group, mask, up, tags_above))
    bits = lambda m, k: ((m[:, None] >> np.arange(k)) & 1).astype(np.float64)

    def rows(at: int, to: int) -> np.ndarray:
        some = slice(at, to)
        return np.concatenate([np.eye(_N_TAGS)[group_a[some]], bits(mask_a[some], _N_WORDS + _N_HASHED), bits(up_a[some], _N_WORDS), bits(above_a[some], _N_TAGS), np.stack([c[some] for c in rest], axis=1)], axis=1)

    return rows, own_a, sub_a


def decode(page: Page, logit: np.ndarray, own: np.ndarray, sub: np.ndarray) -> np.ndarray:
    """Which nodes are kept: the choice of largest evidence in which kept nodes have kept parents."""
    gain = (logit * (own + 0.25 * sub)).tolist()
    n = len(gain)
    best = gain[:]
    parent = page.parent
    for v in range(n - 1, 0, -1):
        if best[v] > 0:
            best[parent[v]] += best[v]
    kept = np.zeros(n, dtype=bool)
    kept[0] = best[0] > 0
    for v in range(1, n):
        kept[v] = kept[parent[v]] and best[v] > 0
    return kept


# ---- training pages -------------------------------------------------------------------------

def _sentence(r: random.Random, low: int = 4, high: int = 24) -> str:
    words = ["".join(r.choice("aeioulnrstmdpcvbgh") for _ in range(r.randint(1, 9))) for _ in range(r.randint(low, high))]
    return " ".join(words).capitalize() + r.choice([".", ".", ".", "?", "!", ""])


def _prose(r: random.Random, short: bool = False) -> str:
    return " ".join(_sentence(r) for _ in range(1 if short else r.choice([1, 1, 2, 3, 5, 8, 14, 30])))


def _attribute(r: random.Random, group: int, bare: float = 0.2) -> str:
    if r.random() < bare:
        return ""
    word = r.choice(sorted(_WORD_GROUPS[group]))
    return f' {r.choice(["class", "class", "id"])}="{r.choice(["", "site-", "block ", "page-", "js-"])}{word}{r.choice(["", "-box", "-wrap", " col", "-inner", "1"])}"'


def _links(r: random.Random, n: int) -> str:
    items = [f'<a href="/{k}">{_sentence(r, 1, 4).rstrip(".?!")}</a>' for k in range(n)]
    kind = r.random()
    if kind < 0.6:
        return "<ul>" + "".join(f"<li>{i}</li>" for i in items) + "</ul>"
    return r.choice([" | ", " ", "<br>"]).join(items) if kind < 0.85 else "".join(f"<div>{i}</div>" for i in items)


def _noise(r: random.Random) -> str:
    """One boilerplate block."""
    kind = r.randrange(9)
    few = lambda: "".join(f"<p>{_prose(r, r.random() < 0.7)}</p>" for _ in range(r.randint(1, 3))) if r.random() < 0.6 else _prose(r, True)
    if kind == 0:
        return f"<nav{_attribute(r, 1, 0.6)}>{_links(r, r.randint(2, 12))}</nav>" if r.random() < 0.7 else f"<div{_attribute(r, 1, 0)}>{_links(r, r.randint(2, 12))}</div>"
    if kind == 1:
        return f"<header{_attribute(r, 2, 0.6)}><h1>{_sentence(r, 1, 4)}</h1>{_links(r, r.randint(0, 6))}{r.choice(['', few()])}</header>" if r.random() < 0.7 else f"<div{_attribute(r, 2, 0)}>{few()}</div>"
    if kind == 2:
        return f"<footer{_attribute(r, 3, 0.6)}>&copy; {few()}{r.choice(['', _links(r, 4)])}</footer>" if r.random() < 0.75 else f"<div{_attribute(r, 3, 0)}>{few()}</div>"
    if kind == 3:
        body = f"<h3>{_sentence(r, 1, 4)}</h3>" * r.randint(0, 1) + r.choice([few, lambda: _links(r, r.randint(2, 8))])()
        return f"<aside{_attribute(r, 4, 0.5)}>{body}</aside>" if r.random() < 0.6 else f"<div{_attribute(r, 4, 0)}>{body}</div>"
    if kind == 4:
        return f"<{(t := r.choice(['div', 'div', 'section', 'p']))}{_attribute(r, 0, 0)}>{few() if t != 'p' else _prose(r, True)}</{t}>"
    if kind == 5:
        one = lambda: f"<{(t := r.choice(['div', 'li', 'article', 'div']))}{_attribute(r, 5, 0.4)}><b>{_sentence(r, 1, 2)}</b>{''.join(f'<p>{_prose(r, True)}</p>' for _ in range(r.randint(1, 2)))}</{t}>"
        return f"<{(t := r.choice(['section', 'div', 'ul', 'ol']))}{_attribute(r, 5, 0)}>{r.choice(['', '<h2>Comments</h2>'])}{''.join(one() for _ in range(r.randint(1, 6)))}</{t}>"
    if kind == 6:
        return f"<{(t := r.choice(['div', 'section', 'div', 'dialog']))}{_attribute(r, 6, 0)}>{few()}{r.choice(['', '<button>OK</button>'])}</{t}>"
    if kind == 7:
        return f"<form{_attribute(r, 7, 0.4)}><label>{_sentence(r, 1, 3)}</label><input name=q>{r.choice(['', f'<p>{_prose(r, True)}</p>'])}<button>{_sentence(r, 1, 2)}</button></form>"
    return f"<div{_attribute(r, 7, 0)}>{r.choice([few, lambda: _links(r, r.randint(2, 5))])()}</div>"


def training_page(r: random.Random) -> tuple[str, str]:
    """(html, mark): main text carries the mark inside every one of its pieces."""
    mark = "\x02"
    say = lambda short=False: mark + _prose(r, short)

    def part() -> str:
        k = r.random()
        if k < 0.62:
            inner = say()
            if r.random() < 0.15:
                inner = f"<b>{inner}<br>" if r.random() < 0.5 else f"{inner} <a href=#>{say(True)}</a> {say(True)}"
            return f"<p>{inner}" + ("</p>" if r.random() < 0.85 else "")
        if k < 0.72:
            return f"<h{(n := r.randint(2, 4))}>{mark}{_sentence(r, 1, 7)}</h{n}>"
        if k < 0.80:
            return f"<{(t := r.choice(['ul', 'ol']))}>" + "".join(f"<li>{say(True)}</li>" for _ in range(r.randint(2, 6))) + f"</{t}>"
        if k < 0.85:
            return f"<blockquote>{r.choice(['<p>', ''])}{say()}</blockquote>"
        if k < 0.89:
            return "<table>" + "".join(f"<tr><td>{say(True)}</td><td>{say(True)}</td></tr>" for _ in range(r.randint(1, 4))) + "</table>"
        if k < 0.92:
            return f"<figure><figcaption>{say(True)}</figcaption></figure>"
        if k < 0.95:
            return f"<pre>{say()}</pre>"
        return f"<div>{say()}</div>" if r.random() < 0.5 else f"<section><h2>{say(True)}</h2><p>{say()}</p><p>{say()}</p></section>"

    parts = [part() for _ in range(r.choice([1, 1, 2, 3, 5, 9, 16]))] if r.random() < 0.85 else [f"<p>{say(True)}{r.choice(['', '</p>'])}" for _ in range(r.randint(1, 2))]
    for _ in range(r.choice([0, 0, 0, 1, 2])):
        parts.insert(r.randint(0, len(parts)), _noise(r))
    title = f"<h1>{mark}{_sentence(r, 1, 9)}</h1>" if r.random() < 0.85 else ""
    tag = r.choice(["article", "article", "main", "div", "div", "section", "td"])
    names = _attribute(r, 8, 0 if tag in ("div", "td", "section") else 0.5)
    story = f"<{tag}{names}>{title}{''.join(parts)}</{tag}>"
    story = f"<table><tr>{story}</tr></table>" if tag == "td" else story
    if r.random() < 0.4:
        story = f"<{(t := r.choice(['main', 'div', 'div']))}{_attribute(r, 8, 0.4)}>{story}{r.choice(['', _noise(r)])}</{t}>"
    above = "".join(_noise(r) for _ in range(r.choice([0, 1, 2, 3])))
    below = "".join(_noise(r) for _ in range(r.choice([0, 1, 1, 2, 4])))
    body = above + story + below
    if r.random() < 0.3:
        body = f"<div{r.choice(['', ' id=wrapper', ' class=container'])}>{body}</div>"
    return f"<!DOCTYPE html><html><head><title>{_sentence(r)}</title></head><body>{body}" + r.choice(["</body></html>", ""]), mark


@lru_cache(maxsize=1)
def model(pages: int = 1200, seed: int = 11) -> boosting.Boosted:
    r = random.Random(seed)
    xs, ys, ws = [], [], []
    for _ in range(pages):
        source, mark = training_page(r)
        page = Page(source)
        rows, own, sub = features(page)
        x = rows(0, len(own))
        main = np.zeros(len(own))
        for node, text, _ in page.pieces:
            if text and mark in text:
                main[node] += len(text)
        for v in range(len(main) - 1, 0, -1):
            main[page.parent[v]] += main[v]
        some = sub > 0
        xs.append(x[some])
        ys.append((main[some] > 0.3 * sub[some]).astype(float))
        ws.append(0.5 + np.sqrt(np.minimum(sub[some], 400)) / 20)
    return boosting.fit(np.concatenate(xs), np.concatenate(ys), np.concatenate(ws))


def main_texts(sources: list[str | None], trees: boosting.Boosted) -> list[str]:
    pages = [Page(s) if s else None for s in sources]
    found = [features(p) if p else None for p in pages]
    # nodes of all pages in one row, worked on in portions of bounded size
    parts = [(f[0], at, min(at + _NODES, len(f[1]))) for f in found if f for at in range(0, len(f[1]), _NODES)]
    logits, held, size = [np.zeros(0)], [], 0
    for k, (rows, at, to) in enumerate(parts):
        held.append(rows(at, to))
        size += to - at
        if size >= _NODES or k + 1 == len(parts):
            logits.append(trees.logit(np.concatenate(held)))
            held, size = [], 0
    logit, at, out = np.concatenate(logits), 0, []
    for page, f in zip(pages, found):
        if page is None:
            out.append("")
            continue
        out.append("\n".join(page.blocks(decode(page, logit[at : at + len(f[1])], f[1], f[2]))))
        at += len(f[1])
    return out


def extract_pages(pages: DataFrame) -> DataFrame:
    """(page_id, url, text) of every page."""
    trees = model()
    shared = pages.sparkSession.sparkContext.broadcast(trees)
    rows = pages.select(F.struct(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url")).alias("doc_id"), F.col("html").cast("string").alias("text"))

    def make():
        def work(texts: list) -> dict:
            return {"text": [t for at in range(0, len(texts), 64) for t in main_texts(texts[at : at + 64], shared.value)]}

        return work

    return map_texts(rows, make, "text string", key="struct<page_id:long,url:string>").select("doc_id.page_id", "doc_id.url", "text")


def digest(found: DataFrame) -> DataFrame:
    return found.select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))
