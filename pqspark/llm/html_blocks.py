"""HTML to its leaf blocks: runs of text between block-level tags, each with its ancestors."""

from __future__ import annotations

import html
import re
from collections import Counter
from collections.abc import Callable
from dataclasses import dataclass

# Elements of the HTML standard by how they take part
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data dfn em font i img ins del kbd label mark nobr output q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SKIPPED = frozenset("script style noscript template svg math iframe object canvas textarea select option datalist audio video title".split())
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split())

_TAG = re.compile(r"<(?:(!--)|([!?])|(/?)([a-zA-Z][^\s/>]*))")
# the rest of a tag: '>' counts as its end unless it stands in a quoted value; possessive, so that it never goes back
_REST = re.compile(r"""((?:[^>=]++|=(?!\s*["'])|=\s*+(?:"[^"]*"|'[^']*'))*+)>""")
_NAMES = re.compile(r"""(?:^|[\s"'])(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_SPACE = re.compile(r"\s+")


@dataclass(slots=True)
class Block:
    text: str
    marks: frozenset  # of all ancestors
    tag: str  # the innermost ancestor, empty at the top
    linked: int  # characters inside links


def blocks(page: str | None, mark: Callable[[str, str], frozenset]) -> list[Block]:
    """The leaf blocks of a page in order, character references decoded and white space made single.

    mark(tag, names) tells what an ancestor with that tag, and that class, id and
    role in lower case, adds to the marks of the blocks in it.  Time grows with
    the length of the page, whatever it holds: a tag whose quotes never close
    makes all later tags end at the next '>', and an element that never ends is
    looked for once.
    """
    page = page or ""
    out: list[Block] = []
    stack: list[tuple[str, frozenset]] = []
    within: Counter[str] = Counter()
    held: list[str] = []
    endless: set[str] = set()
    linked, in_link, at, loose, last = 0, 0, 0, False, page.rfind(">")

    def close() -> None:
        nonlocal linked
        if held:
            text = _SPACE.sub(" ", html.unescape("".join(held))).strip()
            held.clear()
            if text:
                tag, marks = stack[-1] if stack else ("", frozenset())
                out.append(Block(text, marks, tag, linked))
        linked = 0

    def leave() -> str:
        tag = stack.pop()[0]
        within[tag] -= 1
        return tag

    while True:
        m = _TAG.search(page, at)
        if m is not None and m.start() > last and not m.group(1):
            m = None  # no tag ends any more
        run = page[at : m.start() if m else len(page)]
        if run:
            held.append(run)
            if in_link:
                linked += len(run)
        if m is None:
            break
        if m.group(1):
            end = page.find("-->", m.end())
            at = len(page) if end < 0 else end + 3
            continue
        if m.group(2):
            at = page.index(">", m.end()) + 1
            continue
        rest = None if loose else _REST.match(page, m.end())
        if rest is None:
            loose = True
            end = page.index(">", m.end())
            names_in, at = page[m.end() : end], end + 1
        else:
            names_in, at = rest.group(1), rest.end()
        tag, ends = m.group(4).lower(), bool(m.group(3))
        if tag in SKIPPED and not ends:
            if not names_in.endswith("/") and tag not in endless:
                end = re.compile(rf"</{re.escape(tag)}\s*>", re.I).search(page, at)
                if end is None:
                    endless.add(tag)
                at = end.end() if end else (len(page) if tag in ("script", "style") else at)
            continue
        if tag in INLINE:
            if tag == "br":
                held.append(" ")
            elif tag == "a":
                in_link = 0 if ends else 1
            continue
        close()
        if ends:
            if within[tag]:
                while leave() != tag:
                    pass
            continue
        if tag in VOID:
            continue
        if tag in CLOSES_P and stack and stack[-1][0] == "p":
            leave()
        elif tag in ("li", "tr", "td", "th", "dt", "dd") and stack and stack[-1][0] == tag:
            leave()
        names = " ".join(a or b or c for a, b, c in _NAMES.findall(names_in)).lower() if names_in else ""
        marks, own = stack[-1][1] if stack else frozenset(), mark(tag, names)
        stack.append((tag, marks if own <= marks else marks | own))
        within[tag] += 1
    close()
    return out
