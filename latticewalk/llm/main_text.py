"""Main text of web pages by a tree-structured graphical model over the DOM.

Each element is main text or not. Potentials of an element (its tag, words of its class and id, the length
and link share of its text) and of parent and child are counted on labelled pages; sum-product messages up
and down the tree give exact marginals. The labelled pages are made here by a seeded generator, as the tables
bring none: pages of many layouts whose parts are known by construction.
"""

from __future__ import annotations

import random
import re
from collections import Counter
from collections.abc import Iterator
from html import unescape
from math import exp, log

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Possessive, so that what was read once is never read again.
NAME = re.compile(r"[a-zA-Z][^\s/>]*+")
ATTRIBUTES = re.compile(r"(?:[^'\">]++|\"[^\"]*+\"|'[^']*+')*+")
ATTRIBUTE = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.IGNORECASE)
TOKEN = re.compile(r"[a-z]+|[A-Z][a-z]*")
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style title textarea noscript iframe template xmp".split())
RAW_ENDS = {name: re.compile(rf"</{name}(?=[\s/>])", re.IGNORECASE) for name in RAW}
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol p pre search section summary table tbody td tfoot th thead tr ul caption option select".split())
#: Marks of labelled pages: from here on main text (1), or no longer (0); in a declaration, the state of the page as such.
MARK = re.compile(r'data-main="([01])"')
#: Elements whose share of links counts by tag, those at the top of a page, and those that texts are written in.
LINKED, TOP = ("p", "li", "div", "section", "ul"), ("#root", "html", "body")
FLOW = frozenset("p h1 h2 h3 h4 h5 h6 ul ol blockquote pre table dl figure".split())
#: An opening tag ends these open elements, up to an element that holds them.
ENDS = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"}), "body": ({"head"}, {"html"})}
HOLDS_P = frozenset("article aside body blockquote div section td th li table main form figure header footer nav dd button".split())


def tags(html: str) -> Iterator[tuple[int, int, bool, str, str]]:
    """start, end, whether it closes, name and attributes of each tag; name is empty for comments and declarations.

    One pass, in time linear in the page. What is never closed reaches to the end of the page; a quote that is never
    closed is a plain character, so the tag ends at the next `>`.
    """
    at, last = 0, html.rfind(">")
    while True:
        start = html.find("<", at)
        if start < 0:
            return
        closes = html.startswith("/", start + 1)
        name = NAME.match(html, start + 1 + closes)
        if name:
            if start > last:
                yield start, len(html), closes, "", ""
                return
            end = ATTRIBUTES.match(html, name.end()).end()
            if end >= len(html) or html[end] != ">":
                end = html.find(">", name.end())
            yield start, end + 1, closes, name[0].lower(), html[name.end() : end]
            at = end + 1
        elif closes or html.startswith(("!", "?"), start + 1):
            opened, close = next((x for x in (("<!--", "-->"), ("<![CDATA[", "]]>")) if html.startswith(x[0], start)), ("<!", ">"))
            end = html.find(close, start + len(opened))
            at = end + len(close) if end >= 0 else len(html)
            yield start, at, False, "", html[start:at] if close == ">" else ""
        else:
            at = start + 1


class Page:
    """Elements in document order: parent, tag, hint tokens, and the runs of text with the element that holds each."""

    def __init__(self, html: str):
        self.parent, self.tag, self.hints = [-1], ["#root"], [()]
        self.runs: list[tuple[int, str | None]] = []  # (element, text); text None: a block begins or ends there
        self.marks: dict[int, int] = {}  # of labelled pages
        stack, at = [0], 0
        for start, end, closes, name, attributes in tags(html):
            if start < at:  # within the raw text of an element
                continue
            self.text(stack[-1], html[at:start])
            at = end
            mark = MARK.search(attributes) if "data-main=" in attributes else None
            if not name:
                if mark:
                    self.marks[0] = int(mark[1])
                continue
            if closes:
                self.close(stack, name)
                continue
            if name in BLOCK:
                self.end(stack, {"p"}, HOLDS_P)
            if name in ENDS:
                self.end(stack, *ENDS[name])
            me = len(self.tag)
            self.parent.append(stack[-1])
            self.tag.append(name)
            self.hints.append(tuple({t.lower() for a in ATTRIBUTE.finditer(attributes) for t in TOKEN.findall(a[2] or a[3] or a[4] or "")}) if "=" in attributes else ())
            if mark:
                self.marks[me] = int(mark[1])
            if name in BLOCK:
                self.runs.append((me, None))
            if name == "br":
                self.runs.append((stack[-1], " "))
            if name in RAW:
                close = RAW_ENDS[name].search(html, at)
                at = len(html) if not close else html.find(">", close.end()) + 1 or len(html)
            elif name not in VOID and (name in BLOCK or not attributes.endswith("/")):
                stack.append(me)
        self.text(stack[-1], html[at:])

    def text(self, holder: int, text: str) -> None:
        if text:
            self.runs.append((holder, unescape(text) if "&" in text else text))

    def end(self, stack: list[int], names: set[str], within: frozenset | set) -> None:
        for k in range(len(stack) - 1, 0, -1):
            tag = self.tag[stack[k]]
            if tag in names:
                self.pop(stack, k)
                return
            if tag in within:
                return

    def close(self, stack: list[int], name: str) -> None:
        for k in range(len(stack) - 1, 0, -1):
            if self.tag[stack[k]] == name:
                self.pop(stack, k)
                return

    def pop(self, stack: list[int], k: int) -> None:
        for me in stack[k:]:
            if self.tag[me] in BLOCK:
                self.runs.append((me, None))
        del stack[k:]

    def features(self) -> list[list[tuple]]:
        n = len(self.tag)
        own, whole, linked, inside = [0] * n, [0] * n, [0] * n, [False] * n
        for i in range(1, n):
            inside[i] = inside[self.parent[i]] or self.tag[i] == "a"
        for i, text in self.runs:
            if text:
                size = len(text) - (text.isspace() and len(text))
                own[i] += size
                if inside[i]:
                    linked[i] += size
        for i in range(n - 1, -1, -1):
            whole[i] += own[i]
            if i:
                whole[self.parent[i]] += whole[i]
                linked[self.parent[i]] += linked[i]
        out = []
        for i in range(n):
            share = "none" if not whole[i] else "high" if linked[i] * 2 > whole[i] else "some" if linked[i] * 5 > whole[i] else "low"
            length = 0 if not whole[i] else 1 if whole[i] < 20 else 2 if whole[i] < 80 else 3 if whole[i] < 400 else 4
            tag = self.tag[i]
            if tag in ("#root", "body"):  # by the share of the page's text that it holds itself
                tag += " none" if not own[i] else " most" if own[i] * 2 > whole[i] else " some"
            found = [("tag", tag), ("links", tag in LINKED and tag, share), ("length", length), *(("hint", h) for h in self.hints[i])]
            if tag in BLOCK and i and self.tag[self.parent[i]] in TOP:
                found.append(("top", self.tag[self.parent[i]], tag in FLOW))
            out.append(found)
        return out


class TreeModel:
    """Node and edge potentials, in logs, of the states 0 (other) and 1 (main text)."""

    def __init__(self, pages: list[str], smooth: float = 0.5):
        """pages: html whose main elements carry a MARK."""
        seen, edges, kinds, roots = Counter(), Counter(), Counter(), Counter()
        for html in pages:
            page = Page(html)
            state = [page.marks.get(0, 0)] + [0] * (len(page.tag) - 1)
            roots[state[0]] += 1
            for i in range(1, len(page.tag)):
                state[i] = page.marks.get(i, state[page.parent[i]])
                edges[state[page.parent[i]], state[i]] += 1
            for s, features in zip(state, page.features(), strict=True):
                for f in features:
                    seen[f, s] += 1
                    kinds[f[0], s] += 1
        values = Counter(f[0] for f in {f for f, _ in seen})
        self.node = {}
        for f in {f for f, _ in seen}:
            p = [(seen[f, s] + smooth) / (kinds[f[0], s] + smooth * values[f[0]]) for s in (0, 1)]
            self.node[f] = log(p[1] / p[0])
        self.root = log((roots[1] + smooth) / (roots[0] + smooth))
        self.edge = [[log((edges[s, t] + smooth) / (edges[s, 0] + edges[s, 1] + 2 * smooth)) for t in (0, 1)] for s in (0, 1)]

    def marginals(self, page: Page) -> list[float]:
        """P(main text) of each element, by messages from leaves to the root and back."""
        n, get = len(page.tag), self.node.get
        local = [sum(get(f, 0.0) for f in features) for features in page.features()]
        (e00, e01), (e10, e11) = self.edge
        up0, up1 = [0.0] * n, local[:]  # log belief of the subtree given the element's state
        m0, m1 = [0.0] * n, [0.0] * n
        for i in range(n - 1, 0, -1):
            a, b = up0[i] + e00, up1[i] + e01
            m0[i] = (a if a > b else b) + log(1 + exp(-abs(a - b)))
            a, b = up0[i] + e10, up1[i] + e11
            m1[i] = (a if a > b else b) + log(1 + exp(-abs(a - b)))
            p = page.parent[i]
            up0[p] += m0[i]
            up1[p] += m1[i]
        belief = [0.0] * n  # log odds with all messages
        belief[0] = up1[0] - up0[0] + self.root
        for i in range(1, n):
            p = page.parent[i]
            odds = belief[p] - (m1[i] - m0[i])  # the parent's without this child
            q1 = 1 / (1 + exp(-odds)) if odds > -700 else 0.0
            d1 = log((1 - q1) * exp(e01) + q1 * exp(e11))
            d0 = log((1 - q1) * exp(e00) + q1 * exp(e10))
            belief[i] = up1[i] - up0[i] + d1 - d0
        return [1 / (1 + exp(-b)) if b > -700 else 0.0 for b in belief]

    def extract(self, html: str | None) -> str:
        if not html:
            return ""
        page = Page(html)
        main = [p > 0.5 for p in self.marginals(page)]
        blocks, now = [], []
        for i, text in [*page.runs, (0, None)]:
            if text is None:
                if now:
                    line = " ".join("".join(now).split())
                    if line:
                        blocks.append(line)
                    now = []
            elif main[i]:
                now.append(text)
        return "\n".join(blocks)


def labelled_pages(n: int = 400, seed: int = 5) -> list[str]:
    """Pages of many layouts with data-main marks on the elements where main text begins (1) or is left (0)."""
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdefghijklmnoprstuvyé") for _ in range(r.randint(1, 9)))
    words = lambda n: " ".join(word() for _ in range(n))
    link = lambda: f'<a href="/{word()}">{words(r.randint(1, 3))}</a>'

    def prose() -> str:
        n = r.choice((1, 1, 2, 4, 8, 20, 40, 90))
        text = words(n)
        if r.random() < 0.2:
            text += f" {link()} " + words(r.randint(1, 20))
        if r.random() < 0.25:
            tag = r.choice(("b", "i", "em", "strong", "span", "code"))
            text = f"<{tag}>{text}" + (f"</{tag}>" if r.random() < 0.6 else "<br>")
        return text

    def other(kind: str, mark: str) -> str:
        links = "".join(f"<li>{link()}</li>" for _ in range(r.randint(2, 8)))
        named = lambda *names: r.choice((f' class="{r.choice(names)}"', f' id="{r.choice(names)}"', f' class="{r.choice(names)} {word()}"'))
        return {
            "nav": lambda: r.choice((f"<nav{mark}><ul>{links}</ul></nav>", f"<div{named('menu', 'nav', 'navbar', 'breadcrumb', 'navigation')}{mark}><ul>{links}</ul></div>", f"<ul{named('menu', 'nav', 'pagination', 'links')}{mark}>{links}</ul>")),
            "header": lambda: r.choice((f"<header{mark}><div>{words(3)}</div>{link()}</header>", f"<div{named('header', 'masthead', 'topbar', 'banner')}{mark}>{words(4)}</div>")),
            "footer": lambda: r.choice((f"<footer{mark}>&copy; {words(r.randint(2, 30))}</footer>", f"<footer{mark}><p>{words(8)}</p>{link()}</footer>", f"<div{named('footer', 'copyright', 'legal')}{mark}><p>{words(9)}</p></div>")),
            "aside": lambda: r.choice((f"<aside{mark}><p>{words(20)}</p><ul>{links}</ul></aside>", f"<div{named('sidebar', 'related', 'widget', 'rail', 'recommended')}{mark}><h3>{words(2)}</h3><ul>{links}</ul></div>")),
            "ad": lambda: f"<{(t := r.choice(('div', 'div', 'section', 'p', 'span', 'aside')))}{named('ad', 'ads', 'advert', 'sponsored', 'promo', 'advertisement', 'sponsor')}{mark}>{words(r.randint(1, 30))}</{t}>",
            "notice": lambda: f"<div{named('cookie', 'notice', 'consent', 'alert', 'popup', 'newsletter', 'subscribe', 'modal')}{mark}><p>{words(r.randint(3, 25))}</p>" + r.choice(("", "<button>" + words(1) + "</button>")) + "</div>",
            "form": lambda: f"<form{mark}><label>{words(2)}</label><input type=text><select><option>{words(1)}<option>{words(1)}</select><button>{words(1)}</button></form>",
            "share": lambda: f"<div{named('share', 'social', 'tags', 'toolbar')}{mark}>{link()}{link()}</div>",
            "comments": lambda: r.choice((f"<section{named('comments', 'comment', 'replies', 'discussion')}{mark}><h2>{words(2)}</h2>" + "".join(f'<div class="comment"><p>{words(r.randint(1, 40))}</p></div>' for _ in range(r.randint(1, 5))) + "</section>", f"<ol{named('comments', 'commentlist', 'replies')}{mark}>" + "".join(f"<li>{words(r.randint(1, 30))}</li>" for _ in range(3)) + "</ol>")),
        }[kind]()

    def part() -> str:
        """A part of an article: most often a paragraph."""
        close = "</p>" if r.random() < 0.85 else ""
        if r.random() < 0.8:
            return f"<p>{prose()}{close}"
        return r.choice((
            lambda: f"<h2>{words(3)}</h2>",
            lambda: "<ul>" + "".join(f"<li>{prose()}</li>" for _ in range(3)) + "</ul>",
            lambda: f"<blockquote><p>{prose()}</p></blockquote>",
            lambda: f"<div>{prose()}</div>",
            lambda: f"<pre>{words(9)}</pre>",
            lambda: f"<table><tr><td>{words(2)}<td>{words(3)}</table>",
            lambda: f"<section><h3>{words(2)}</h3><p>{prose()}</section>",
            lambda: f"<figure><img src=x><figcaption>{words(6)}</figcaption></figure>",
        ))()

    def plain() -> str:
        """A page of nothing but text: in a body, in paragraphs alone, or without any element."""
        text = "".join(f"<p>{prose()}</p>" for _ in range(r.randint(1, 9)))
        return r.choice((
            lambda: f'<html><head><title>x</title></head><body data-main="1">{text}</body></html>',
            lambda: f'<html><body data-main="1">{words(r.randint(1, 60))}</body></html>',
            lambda: f'<!data-main="1">{text}',
            lambda: f'<!data-main="1">{words(r.randint(1, 60))}' + r.choice(("", f"<br>{words(9)}", f" <b>{words(2)}</b> {words(5)}")),
        ))()

    mains = (
        lambda body, name: f'<article data-main="1">{body}</article>',
        lambda body, name: f'<article class="{name}" data-main="1">{body}</article>',
        lambda body, name: f'<main data-main="1">{body}</main>',
        lambda body, name: f'<main><article data-main="1">{body}</article></main>',
        lambda body, name: f'<div id="{name}" data-main="1">{body}</div>',
        lambda body, name: f'<div class="{name}-body" data-main="1">{body}</div>',
        lambda body, name: f'<section class="{name}" data-main="1">{body}</section>',
    )
    pages = []
    for _ in range(n):
        if r.random() < 0.12:
            pages.append(plain())
            continue
        parts = [f"<h1>{words(r.randint(1, 12))}</h1>"] if r.random() < 0.9 else []
        parts += [part() for _ in range(r.randint(1, 25))]
        for kind in ("ad", "share", "form", "aside", "notice", "comments"):
            if r.random() < 0.12:
                parts.insert(r.randint(0, len(parts)) if kind in ("ad", "aside", "notice") else len(parts), other(kind, ' data-main="0"'))
        name = r.choice(("content", "post", "entry", "article", "story", "main", "text"))
        main = r.choice(mains)("".join(parts), name)
        outer = [k for k in ("nav", "header", "footer", "aside", "ad", "notice", "form", "comments", "share") if r.random() < 0.55]
        before = [other(k, "") for k in outer if k in ("nav", "header", "ad", "notice") or k != "footer" and r.random() < 0.3]
        after = [other(k, "") for k in outer if k in ("footer", "aside", "comments", "form", "share", "nav", "ad")]
        r.shuffle(before)
        middle = "".join(before) + main + "".join(after)
        if r.random() < 0.3:
            middle = f'<div class="{r.choice(("wrapper", "page", "container", "layout"))}">{middle}</div>'
        head = f"<head><meta charset=utf-8><title>{words(4)}</title><style>p{{}}</style><script>x()</script></head>"
        pages.append(f"<!DOCTYPE html><html>{head}<body>{middle}</body></html>")
    return pages


def extract_pages(pages: DataFrame, model: TreeModel | None = None) -> DataFrame:
    """page_id, url, text (empty if none), n_chars: the main text of each page's whole html (null: empty).

    Repeated rows and null ids give a row each; other columns are left out. An empty table gives no rows.
    """
    model = model or TreeModel(labelled_pages())

    @F.pandas_udf("string")
    def extract(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for part in parts:
            yield pd.Series([model.extract(h if isinstance(h, str) else None) for h in part], dtype=object)

    return pages.select("page_id", "url", extract("html").alias("text")).withColumn("n_chars", F.length("text").cast("long"))
