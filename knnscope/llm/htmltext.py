"""Main text of HTML pages: flat text blocks, classified by a decision tree from the shallow features of neighbours.

A page is a sequence of blocks, stretches of text between block-level tags. Each block is described by its number of
words and link density, those of the blocks before and after it, whether it is a heading, and by how its surroundings
speak for or against it: what the tags around it are, and the words of their classes and ids, each with the log odds that it
has in a labelled table. The table is small and made here: pages written from patterns, whose main blocks are known. A
decision tree grown on the table's blocks decides which blocks are main text; what no tag or class tells is left to words,
links and neighbours.

Defined cases: NULL and empty pages have the empty string; unclosed tags end where their parents do; scripts, styles and
comments without an end reach to the end of the page, and so does text after the last ``>``; repeated rows repeat; extra
columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame

from knnscope.llm.common import map_rows

SCHEMA = "page_id long, url string, text string, n_chars long"
TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>"
    r"|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)([^>]*)>|<[!?][^>]*>|([^<]+|<)",
    re.S,
)
ATTRIBUTE = re.compile(r"\b(?:class|id|role|aria-label)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
#: Fixed lists of tag names.
RAW = {"script", "style", "noscript", "template", "svg", "iframe", "textarea", "select", "button", "object", "math", "title"}
INLINE = {
    "a", "abbr", "acronym", "b", "bdi", "bdo", "big", "br", "cite", "code", "data", "del", "dfn", "em", "font", "i", "img",
    "input", "ins", "kbd", "label", "mark", "q", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time",
    "tt", "u", "var", "wbr",
}
VOID = {"br", "img", "input", "wbr", "hr", "meta", "link", "area", "base", "col", "embed", "source", "track", "param"}
ARTICLE = {"article", "main"}
#: Tags of single stretches of text, which stand in articles and beside them alike: only their classes say something.
PLAIN = {
    "p", "h1", "h2", "h3", "h4", "h5", "h6", "ul", "ol", "li", "dl", "dt", "dd", "table", "thead", "tbody", "tr", "th", "td", "pre", "blockquote",
    "figure", "figcaption", "html", "body", "center", "hgroup", "caption",
}
HEADINGS = {"h1", "h2", "h3", "h4", "h5", "h6"}
ENDS_P = {
    "address", "article", "aside", "blockquote", "div", "dl", "fieldset", "figure", "footer", "form", "h1", "h2", "h3", "h4",
    "h5", "h6", "header", "hr", "main", "menu", "nav", "ol", "p", "pre", "section", "table", "ul",
}
PART = re.compile(r"[a-z]+")
CAMEL = re.compile(r"([a-z])([A-Z])")


def names(tag: str, attributes: str, inside: bool) -> list[str]:
    """What a tag says about what it holds: its own name, and the words of its classes, ids and roles.

    A tag inside the article is another one than outside. Names like ``with-sidebar`` speak of the page, not of their content.
    """
    found = [] if tag in INLINE or tag in PLAIN else [f"<{tag}>" + (" inside" if inside else "")]
    if "=" in attributes:
        for m in ATTRIBUTE.finditer(attributes):
            for name in CAMEL.sub(r"\1-\2", m[1] or m[2] or m[3] or "").lower().split():
                words = PART.findall(name)
                if words and words[0] not in ("has", "no", "with", "without"):
                    found += words
    return found


@dataclass
class Block:
    text: str
    words: int
    link_density: float
    heading: bool
    around: tuple[tuple[str, ...], ...]


def blocks(page: str) -> list[Block]:
    """The text blocks of a page in order."""
    found: list[Block] = []
    stack: list[tuple[str, tuple[str, ...], bool]] = []  # tag, its names, whether it is an article
    open_tags: Counter = Counter()
    text: list[str] = []
    links, in_link, article, heading = 0, 0, 0, False

    def flush() -> None:
        nonlocal links
        if text:
            words = html.unescape("".join(text)).split()
            if words:
                around = tuple(own for _, own, _ in stack if own)
                found.append(Block(" ".join(words), len(words), min(1.0, links / len(words)), heading, around))
            text.clear()
        links = 0

    def push(tag: str, own: list[str]) -> None:
        nonlocal article
        stack.append((tag, tuple(own), tag in ARTICLE))
        open_tags[tag] += 1
        article += tag in ARTICLE

    def pop() -> None:
        nonlocal article
        tag, _, was_article = stack.pop()
        open_tags[tag] -= 1
        article -= was_article

    at, n, last = 0, len(page), page.rfind(">")
    while at < n:
        if at > last:  # no tag can end any more
            text.append(page[at:])
            break
        m = TOKEN.match(page, at)
        if m is None:
            at += 1
            continue
        at = m.end()
        if (run := m[7]) is not None:
            text.append(run)
            if in_link:
                links += len(html.unescape(run).split())
            continue
        tag = m[2] or m[5]
        if tag is None:
            continue  # a comment or declaration
        tag, closing, attributes = tag.lower(), (m[1] or m[4]) == "/", m[3] or m[6] or ""
        if tag in RAW:
            if tag != "title":
                text.append(" ")
            if not closing and not attributes.endswith("/"):
                end = re.compile(f"</{tag}\\s*>", re.I).search(page, at)
                at = end.end() if end else n
            continue
        if tag in INLINE:
            if tag == "a":
                in_link = 0 if closing else 1
            elif tag == "br":
                text.append(" ")
            if not closing and tag not in VOID and tag != "a" and (own := names(tag, attributes, article > 0)):
                flush()
                push(tag, own)
            elif closing and stack and stack[-1][0] == tag:
                flush()
                pop()
            continue
        flush()
        heading = tag in HEADINGS and not closing
        if closing:
            if open_tags[tag]:
                in_link = 0
                while stack[-1][0] != tag:
                    pop()
                pop()
            continue
        if tag in ENDS_P and any(t == "p" for t, _, _ in stack[-3:]):
            while stack[-1][0] != "p":
                pop()
            pop()
        if tag == "li":
            while stack and stack[-1][0] in ("p", "li"):
                pop()
        if tag not in VOID:
            push(tag, names(tag, attributes, article > 0))
    flush()
    return found


FEATURES = (
    "words", "link_density", "words_before", "link_density_before", "words_after", "link_density_after", "heading",
    "against", "in_favour", "behind",
)


def features(found: list[Block], odds: dict[str, float]) -> np.ndarray:
    """One row for each block; beyond the page there are no words.

    ``against`` and ``in_favour`` are the least and greatest log odds of what stands around a block, ``behind`` is by how
    much ``in_favour`` falls short of the page's best.
    """
    w = np.array([0, *(b.words for b in found), 0], float)
    d = np.array([0, *(b.link_density for b in found), 0], float)
    memo: dict[tuple, tuple[float, float]] = {}
    for b in found:
        if b.around not in memo:
            own = [odds.get(name, 0.0) for tag in b.around for name in tag]
            memo[b.around] = min(own, default=0.0), max(own, default=0.0)
    low, high = np.array([memo[b.around] for b in found], float).reshape(-1, 2).T
    best = high[low >= -1].max(initial=0.0)
    heading = np.array([b.heading for b in found], float)
    return np.stack([w[1:-1], d[1:-1], w[:-2], d[:-2], w[2:], d[2:], heading, low, high, np.maximum(best - high, 0)], 1)


class DecisionTree:
    """Axis-parallel splits that lower the Gini impurity most, to a small depth."""

    def __init__(self, x: np.ndarray, y: np.ndarray, depth: int = 12, least: int = 2):
        self.root = self._grow(x, y, depth, least)

    def _grow(self, x, y, depth, least):
        p = float(y.mean())
        if depth == 0 or len(y) < 2 * least or p in (0.0, 1.0):
            return p
        best = (len(y) * p * (1 - p) - 1e-9, None)
        for j in range(x.shape[1]):
            order = np.argsort(x[:, j], kind="stable")
            v, ones = x[order, j], np.cumsum(y[order])
            cut = np.flatnonzero(v[:-1] < v[1:]) + 1
            cut = cut[(cut >= least) & (cut <= len(y) - least)]
            if len(cut):
                a, b = ones[cut - 1], ones[-1] - ones[cut - 1]
                loss = a * (1 - a / cut) + b * (1 - b / (len(y) - cut))
                k = int(loss.argmin())
                if loss[k] < best[0]:
                    best = (float(loss[k]), (j, float((v[cut[k] - 1] + v[cut[k]]) / 2)))
        if best[1] is None:
            return p
        j, t = best[1]
        low = x[:, j] <= t
        return j, t, self._grow(x[low], y[low], depth - 1, least), self._grow(x[~low], y[~low], depth - 1, least)

    def predict(self, x: np.ndarray) -> np.ndarray:
        out = np.empty(len(x))

        def walk(node, rows):
            if isinstance(node, float):
                out[rows] = node
            elif len(rows):
                j, t, low, high = node
                left = x[rows, j] <= t
                walk(low, rows[left])
                walk(high, rows[~left])

        walk(self.root, np.arange(len(x)))
        return out


#: Stands before each word of main text in a page of the labelled table.
MAIN = "\ue000"
#: Fixed names that pages use for what isn't the article, by kind, and for the article.
OTHERS = {
    "menu": "nav navbar navigation menu masthead topbar toolbar header breadcrumb breadcrumbs",
    "short": "footer contentinfo legal copyright tags byline pager pagination teaser",
    "advert": "ad ads adv advert adverts advertisement banner promo sponsor sponsored",
    "notice": "cookie cookies consent gdpr notice alert modal popup newsletter subscribe signup login search",
    "comments": "comment comments reply replies discussion responses disqus reader readers",
    "links": "related complementary recommended sidebar widget social share sharing",
}
OWN = "content post entry story body text article main"


def labelled_pages(pages: int = 900, seed: int = 11) -> list[str]:
    """Pages from patterns, with tags and classes that say what they hold or without. Lengths, link densities and order are
    drawn, not taken from any data that is to be judged."""
    rng = np.random.default_rng(seed)
    chance = lambda p: rng.random() < p
    pick = lambda words: str(rng.choice(words.split()))

    def words(low: int, high: int, main: bool = False, links: float = 0.0) -> str:
        n = int(rng.integers(low, high + 1))
        linked = round(links * n)
        plain = " ".join([("" if not main else MAIN) + "w"] * (n - linked))
        return plain + (f" <a href=x>{' '.join(['w'] * linked)}</a>" if linked else "")

    def other(kind: str, tags: str, inner: str, says: bool) -> str:
        """What isn't the article, in a tag that says so, or with a class that does, or neither."""
        if not says:
            return f"<div>{inner}</div>"
        if chance(0.3):
            title = pick("h1 h2 h3 h4")
            inner = f"<{title}>{words(1, 4)}</{title}>" + inner
        tag = pick(tags) if chance(0.5) else ""
        name = "" if tag not in ("", "section", "div") and chance(0.5) else f" {pick('class id')}='{pick(OTHERS[kind])}{pick('-box -area -1 - -') if chance(0.3) else ''}'"
        return f"<{tag or 'div'}{name}>{inner}</{tag or 'div'}>"

    def list_of_links() -> str:
        items = [words(1, 5, links=1.0 if chance(0.9) else 0.5) for _ in range(rng.integers(1, 8))]
        return "<ul>" + "".join(f"<li>{x}</li>" for x in items) + "</ul>" if chance(0.7) else "".join(f"<p>{x}</p>" for x in items)

    def beside(says: bool) -> list[str]:
        some = []
        if chance(0.5):
            some.append(other("advert", "aside", f"<p>{words(2, 40 if says else 10, links=rng.random() * 0.6)}</p>" if chance(0.5) else words(2, 40 if says else 10), says))
        if chance(0.35):
            some.append(other("notice", "dialog form aside fieldset", f"<p>{words(3, 50 if says else 10)}</p>", says))
        if chance(0.3):
            some.append(other("links", "aside nav", list_of_links(), says))
        return some

    found = []
    for _ in range(pages):
        tagged, says, bare = chance(0.5), chance(0.8), chance(0.25)
        body = [f"<h1>{words(1, 14, True)}</h1>"] if chance(0.75) else []
        for _ in range(rng.integers(1, 14) if chance(0.7) else 1):
            short = chance(0.35 if tagged else 0.04)
            inner = words(1, 12, True) if short else words(15, 220, True, rng.random() * 0.15)
            tag = "p" if chance(0.85) else pick("blockquote pre div section figure dd")
            body.append(f"<{tag}>{inner}</{tag}>")
            if chance(0.1):
                title = pick("h2 h3 h4")
                body.append(f"<{title}>{words(1, 9, True)}</{title}>")
            if tagged and chance(0.15):
                group, item = [("ul", "li"), ("ol", "li"), ("table", "td")][int(rng.integers(3))]
                items = "".join(f"<{item}>{words(1, 25, True)}</{item}>" for _ in range(rng.integers(1, 6)))
                body.append(f"<{group}>{'<tr>' if item == 'td' else ''}{items}{'</tr>' if item == 'td' else ''}</{group}>")
            if chance(0.12):
                body += beside(True)
        if tagged and chance(0.3):
            body[0] = f"<header>{body[0]}</header>"
        if tagged and chance(0.25):
            body.append(other("comments", "section aside div", "".join(f"<p>{words(3, 70)}</p>" for _ in range(rng.integers(1, 5))), True))
        if tagged:
            tag = pick("article main div section") if says else pick("article main")
            name = f" {pick('class id')}='{pick(OWN)}'" if tag in ("div", "section") or chance(0.3) else ""
            article = f"<{tag}{name}>{''.join(body)}</{tag}>"
        else:
            article = "".join(body) if chance(0.5) else f"<div>{''.join(body)}</div>"
        before, after = [], []
        if not bare:
            if chance(0.8):
                before.append(other("menu", "nav header menu", list_of_links(), says))
            before += beside(says)
            after += beside(says)
            if chance(0.4):
                after.append(other("comments", "aside section div", "".join(f"<p>{words(3, 70)}</p>" for _ in range(rng.integers(1, 4))), True))
            if chance(0.8):
                after.append(other("short", "footer", words(3, 14, links=rng.random() * 0.5), says))
        found.append("<body>" + "".join([*before, article, *after]) + "</body>")
    return found


@dataclass
class Classifier:
    odds: dict[str, float]
    tree: DecisionTree

    def main_text(self, page: str | None) -> str:
        found = blocks(page or "")
        if not found:
            return ""
        keep = self.tree.predict(features(found, self.odds)) >= 0.5
        return "\n\n".join(b.text for b, k in zip(found, keep) if k)


def fit(pages: list[str], least: int = 3) -> Classifier:
    """Learn from pages whose main text is marked: first the odds of each name, then the tree.

    A name that fewer than ``least`` pages use has no odds.
    """
    table = [blocks(page) for page in pages]
    labels = [[MAIN in b.text for b in found] for found in table]
    counts: dict[str, list[int]] = {}
    used: Counter = Counter()
    for found, own in zip(table, labels):
        for b, y in zip(found, own):
            for name in {x for tag in b.around for x in tag}:
                counts.setdefault(name, [0, 0])[y] += 1
        used.update({x for b in found for tag in b.around for x in tag})
    total = Counter(y for own in labels for y in own)
    odds = {
        name: float(np.log((n1 + 0.5) / (total[True] + 1)) - np.log((n0 + 0.5) / (total[False] + 1)))
        for name, (n0, n1) in counts.items()
        if used[name] >= least
    }
    x = np.concatenate([features(found, odds) for found in table])
    return Classifier(odds, DecisionTree(x, np.array([y for own in labels for y in own], float)))


@lru_cache(maxsize=1)
def classifier() -> Classifier:
    return fit(labelled_pages())


def main_text(page: str | None) -> str:
    return classifier().main_text(page)


def extract(pages: DataFrame) -> DataFrame:
    """``page_id, url, text, n_chars`` of every page, from the whole HTML."""

    own = classifier()  # small, so it travels with the code

    def kernel(batches):
        for rows in batches:
            texts = [own.main_text(page) for _, _, page in rows]
            yield {
                "page_id": [r[0] for r in rows], "url": [r[1] for r in rows], "text": texts, "n_chars": [len(t) for t in texts],
            }

    return map_rows(pages, ["page_id", "url", "html"], kernel, SCHEMA)
