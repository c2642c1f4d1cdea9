"""Labelled pages to train the extraction field on: made from many layouts, with invented words.

A page is a list of (html piece, main text or not) that the layouts put
together; the label of a block is that of the piece which its text comes from.
"""

from __future__ import annotations

import random

from pqspark.llm.html_blocks import Block
from pqspark.llm.html_extract import leaf_blocks

SYLLABLES = "ba co di fu ge ho ji ka lo mu ne po qui ra si to u ve wo xa ye zo sch ción eau tre al en or is".split()


class Page:
    def __init__(self, rng: random.Random):
        self.rng, self.made, self.main = rng, [], set()

    def words(self, least: int, most: int) -> str:
        r = self.rng
        return " ".join("".join(r.choices(SYLLABLES, k=r.randint(1, 4))) for _ in range(r.randint(least, most)))

    def sentence(self, least: int = 3, most: int = 18) -> str:
        text = self.words(least, most)
        if self.rng.random() < 0.4:
            text = text.replace(" ", ", ", 1)
        return text[0].upper() + text[1:] + self.rng.choice("....?!")

    def text(self, sentences: int) -> str:
        return " ".join(self.sentence() for _ in range(sentences))

    def add(self, *pieces: str) -> None:
        self.made += pieces

    def untidy(self, text: str) -> str:
        """Text as careless authors leave it: small letters, separators, no full stops, signs, numbers."""
        r = self.rng
        kind = r.randrange(6)
        if kind == 0:
            return text.lower()
        if kind == 1:
            return text.lower().rstrip(".?!") + r.choice(["", " |", " *", " -"])
        if kind == 2:
            return text.replace(" ", " | ").lower()
        if kind == 3:
            return " ".join(w + r.choice(["", "***", "%%%", "$$$"]) for w in text.split(" "))
        if kind == 4:
            return " ".join(str(r.randrange(10**6)) if r.random() < 0.5 else w for w in text.split(" "))
        return "- " + text

    def leaf(self, tag: str, text: str, main: bool, attrs: str = "", decorate: bool = True) -> None:
        shown = text
        if decorate and self.rng.random() < 0.25 and " " in text:
            head, _, rest = text.partition(" ")
            shown = self.rng.choice([f"<b>{head}</b> {rest}", f'<a href="/x">{head}</a> {rest}', f"<em>{head} {rest}</em>", f"{head}<br>{rest}", f"<b>{head} {rest}"])
        ends = "" if self.rng.random() < 0.08 and tag in ("p", "li") else f"</{tag}>"
        self.add(f"<{tag}{attrs}>{shown}{ends}")
        if main:
            self.main.add(" ".join(text.split()))


def _links(p: Page, n: int, wrap: str = "li") -> None:
    for _ in range(n):
        p.add(f'<{wrap}><a href="/{p.words(1, 1)}">{p.words(1, 3)}</a></{wrap}>')


def _menu(p: Page) -> None:
    r = p.rng
    opening, closing = r.choice([("<nav>", "</nav>"), ('<div class="menu">', "</div>"), ('<ul id="main-nav">', "</ul>"), ('<div class="breadcrumbs">', "</div>"), ('<nav role="navigation">', "</nav>")])
    p.add(opening, "<ul>")
    _links(p, r.randint(2, 9))
    p.add("</ul>", closing)


def _header(p: Page) -> None:
    r = p.rng
    opening, closing = r.choice([("<header>", "</header>"), ('<div id="header">', "</div>"), ('<div class="site-header masthead">', "</div>"), ('<header class="topbar">', "</header>")])
    p.add(opening)
    p.leaf(r.choice(["h1", "div", "p", "span"]), p.words(1, 4), False)
    if r.random() < 0.5:
        p.leaf("p", p.sentence(2, 7), False)
    if r.random() < 0.5:
        _menu(p)
    p.add(closing)


def _footer(p: Page) -> None:
    r = p.rng
    opening, closing = r.choice([("<footer>", "</footer>"), ('<div id="footer">', "</div>"), ('<div class="site-footer">', "</div>"), ('<footer class="colophon">', "</footer>")])
    p.add(opening)
    if r.random() < 0.4:
        _links(p, r.randint(2, 6), "p")
    text = r.choice(["&copy; {} &middot; {}", "Copyright 2021 {}. {}", "{} All rights reserved. {}", "{} {}"]).format(p.words(1, 2), p.text(r.randint(1, 3)))
    p.add(text if r.random() < 0.5 else f"<p>{text}</p>")
    p.add(closing)


def _aside(p: Page) -> None:
    r = p.rng
    opening, closing = r.choice([("<aside>", "</aside>"), ('<div class="sidebar">', "</div>"), ('<div id="right-rail" class="widget">', "</div>"), ('<section class="related-posts">', "</section>"), ('<div class="recommended">', "</div>")])
    p.add(opening)
    p.leaf(r.choice(["h2", "h3", "h4"]), p.words(1, 3), False)
    if r.random() < 0.6:
        p.add("<ul>")
        _links(p, r.randint(2, 6))
        p.add("</ul>")
    if r.random() < 0.6:
        p.leaf("p", p.text(r.randint(1, 3)), False)
    p.add(closing)


def _advert(p: Page) -> None:
    r = p.rng
    name = r.choice(["ad", "ads", "advert", "ad-slot", "sponsored", "promo", "banner-ad", "advertisement", "ad_unit"])
    body = p.text(r.randint(1, 3))
    p.add(f'<div {r.choice(["class", "id"])}="{name}">', body if r.random() < 0.6 else f"<p>{body}</p>", "</div>")


def _notice(p: Page) -> None:
    r = p.rng
    name = r.choice(["cookie-banner", "consent", "notice", "newsletter-signup", "popup modal", "gdpr", "alert", "subscribe-box", "disclaimer"])
    p.add(f'<div class="{name}"{r.choice(["", " role=dialog", " role=alert"])}>')
    p.leaf(r.choice(["p", "div", "span"]), p.text(r.randint(1, 2)), False)
    if r.random() < 0.5:
        p.add(f"<button>{p.words(1, 2)}</button>")
    p.add("</div>")


def _form(p: Page) -> None:
    r = p.rng
    p.add(r.choice(["<form>", '<form class="search">', '<form id="contact-form" action="/s">']))
    for _ in range(r.randint(1, 3)):
        p.add(f"<{r.choice(['p', 'div'])}><label>{p.words(1, 4)}</label><input name=q>")
    p.add(f"<button>{p.words(1, 2)}</button></form>")


def _comments(p: Page) -> None:
    r = p.rng
    opening, closing = r.choice([('<section class="comments">', "</section>"), ('<div id="comments">', "</div>"), ('<ol class="comment-list">', "</ol>"), ('<div class="reader-comments">', "</div>"), ('<section id="discussion">', "</section>"), ('<div class="replies">', "</div>")])
    p.add(opening)
    if r.random() < 0.5:
        p.leaf(r.choice(["h2", "h3"]), p.words(1, 3), False)
    for _ in range(r.randint(1, 5)):
        kind = r.choice(['<article class="comment">', '<div class="comment">', '<li class="comment">', "<div>"])
        p.add(kind)
        if r.random() < 0.6:
            p.add(f'<div class="author">{p.words(1, 2)}</div>')
        p.leaf("p", p.text(r.randint(1, 4)), False)
        p.add(f"</{kind[1:].split()[0].rstrip('>')}>")
    p.add(closing)


def _body(p: Page) -> None:
    """The article with what may stand between its paragraphs."""
    r = p.rng
    opening, closing = r.choice([
        ("<article>", "</article>"), ("<article>", "</article>"), ("<main>", "</main>"), ('<main><article class="post">', "</article></main>"), ('<div class="post-content">', "</div>"),
        ('<div id="content">', "</div>"), ('<div class="entry-content">', "</div>"), ('<div class="article-body">', "</div>"), ('<section class="story">', "</section>"), ('<div class="main"><div class="text">', "</div></div>"), ("<div>", "</div>"),
    ])
    p.add(opening)
    if r.random() < 0.85:
        title = p.words(1, 9)
        p.leaf(r.choice(["h1", "h1", "h2"]), title.capitalize() + r.choice(["", "."]) if r.random() < 0.7 else p.untidy(title), True)
    care = r.choice([1.0, 1.0, 0.9, 0.5, 0.0])
    for _ in range(r.randint(1, 12)):
        kind = r.random()
        if kind < 0.72:
            text = p.text(r.choice([1, 1, 2, 3, 5, 9]))
            p.leaf("p", text if r.random() < care else p.untidy(text), True)
        elif kind < 0.78:
            p.leaf("p", p.words(1, 3).capitalize() + "." if r.random() < care else p.words(1, 4), True)
        elif kind < 0.83:
            p.leaf(r.choice(["h2", "h3"]), p.words(1, 6).capitalize(), True)
        elif kind < 0.87:
            p.add("<ul>")
            for _ in range(r.randint(2, 4)):
                p.leaf("li", p.sentence(), True)
            p.add("</ul>")
        elif kind < 0.91:
            p.add("<blockquote>")
            p.leaf("p", p.text(2), True)
            p.add("</blockquote>")
        elif kind < 0.94:
            _advert(p)
        elif kind < 0.96:
            _aside(p)
        elif kind < 0.98:
            _notice(p)
        else:
            p.add(f'<div class="share">{p.words(1, 4)}</div>')
    if r.random() < 0.15:
        _comments(p)
    p.add(closing)


def page(rng: random.Random) -> tuple[str, set[str]]:
    """(html, texts of its main blocks)."""
    p = Page(rng)
    title = p.words(2, 7)
    p.add(f'<!DOCTYPE html><html><head><meta charset="utf-8"><title>{title}</title><style>p{{margin:0}}</style><script>var t="</p>";</script></head><body>')
    before = [f for f, chance in ((_notice, 0.2), (_header, 0.45), (_menu, 0.7), (_advert, 0.4), (_form, 0.15), (_aside, 0.15)) if rng.random() < chance]
    rng.shuffle(before)
    for f in before:
        f(p)
    _body(p)
    after = [f for f, chance in ((_comments, 0.35), (_aside, 0.4), (_advert, 0.25), (_form, 0.15), (_notice, 0.15), (_menu, 0.15)) if rng.random() < chance]
    rng.shuffle(after)
    for f in after:
        f(p)
    if rng.random() < 0.85:
        _footer(p)
    p.add("</body></html>")
    return "".join(p.made), p.main


def labelled_pages(n: int, seed: int) -> list[tuple[list[Block], list[int]]]:
    """n pages as blocks with their labels, the same for the same seed."""
    rng, out = random.Random(seed), []
    for _ in range(n):
        html, main = page(rng)
        found = leaf_blocks(html)
        out.append((found, [int(b.text in main) for b in found]))
    return out
