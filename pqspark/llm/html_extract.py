"""HTML extraction by a linear-chain conditional random field over leaf blocks.

Each block has features of its ancestors (tags, and hints in class, id and role),
of its text, and of its place; neighbouring labels have weights of their own.
The field is trained by gradient on labelled pages and decoded by Viterbi.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pqspark.llm.common import lean_batches
from pqspark.llm.html_blocks import Block, blocks

# Tags that make a feature, and hints in class, id and role names
TAGS = tuple("nav header footer aside article main section form ul ol li table td h1 h2 h3 h4 p blockquote figure figcaption dl pre button fieldset menu div body html address details".split())
HINTS = {
    "nav": ("nav", "menu", "breadcrumb", "crumb", "pager", "pagination", "toolbar", "tabs"),
    "header": ("header", "masthead", "topbar", "logo", "site-title", "brand"),
    "footer": ("footer", "foot", "copyright", "legal", "colophon", "contentinfo", "imprint"),
    "side": ("side", "aside", "widget", "related", "recommend", "popular", "trending", "complementary", "more-", "teaser", "rail"),
    "ad": ("ad", "ads", "advert", "sponsor", "promo", "banner", "commercial", "affiliate"),
    "comment": ("comment", "reply", "replies", "discuss", "disqus", "respond", "reader"),
    "notice": ("cookie", "consent", "notice", "alert", "popup", "modal", "gdpr", "disclaimer", "newsletter", "subscribe", "signup", "paywall", "warning", "toast", "dialog"),
    "share": ("share", "social", "follow", "tags", "rating"),
    "form": ("form", "search", "login", "register", "contact"),
    "content": ("article", "content", "post", "entry", "story", "text", "main", "body", "prose"),
}
_HINT_OF = {h: name for name, hs in HINTS.items() for h in hs}
_LONGEST_HINT = max(map(len, _HINT_OF))
_NAME_PART = re.compile(r"[a-z]+")
_NOTE = re.compile(r"©|\(c\)|copyright|all rights reserved|cookie|privacy|subscribe|newsletter|sign up|log ?in|advert|sponsored|reply|comment", re.I)
_DIGIT = re.compile(r"\d+")
_END = re.compile(r"[.!?…:;\"”»)]$")

NAMES = (
    *(f"in:{t}" for t in TAGS),
    *(f"own:{t}" for t in TAGS),
    *(f"hint:{h}" for h in HINTS),
    *(f"words:{k}" for k in range(6)),
    *(f"links:{k}" for k in range(4)),
    "ends", "note", "digits", "capital", "comma", "first", "last", "early", "late", "bias",
)
PLACE = {name: k for k, name in enumerate(NAMES)}


@lru_cache(maxsize=4096)
def _mark(tag: str, names: str) -> frozenset[int]:
    """The features, by number, that an ancestor gives to all blocks in it."""
    found = {f"in:{tag}"}
    for part in _NAME_PART.findall(names):
        for length in range(min(len(part), _LONGEST_HINT), 1, -1):  # a hint may begin or be a part of a name: longest first
            if part[:length] in _HINT_OF and (length > 3 or length == len(part)):
                found.add(f"hint:{_HINT_OF[part[:length]]}")
                break
    return frozenset(PLACE[f] for f in found if f in PLACE)


def leaf_blocks(page: str | None) -> list[Block]:
    return blocks(page, _mark)


def features(page: list[Block]) -> list[list[int]]:
    """The active features of each block, by number."""
    out, n = [], len(page)
    for k, block in enumerate(page):
        text, f = block.text, sorted(block.marks)
        if f"own:{block.tag}" in PLACE:
            f.append(PLACE[f"own:{block.tag}"])
        n_words = text.count(" ") + 1
        f.append(PLACE[f"words:{0 if n_words < 2 else 1 if n_words < 4 else 2 if n_words < 8 else 3 if n_words < 16 else 4 if n_words < 40 else 5}"])
        share = block.linked / len(text)
        f.append(PLACE[f"links:{0 if block.linked == 0 else 1 if share < 0.3 else 2 if share < 0.8 else 3}"])
        if _END.search(text):
            f.append(PLACE["ends"])
        if n_words < 40 and _NOTE.search(text):
            f.append(PLACE["note"])
        if 10 * (len(text) - len(_DIGIT.sub("", text))) > len(text):
            f.append(PLACE["digits"])
        if text[0].isupper():
            f.append(PLACE["capital"])
        if ", " in text:
            f.append(PLACE["comma"])
        if k == 0:
            f.append(PLACE["first"])
        if k == n - 1:
            f.append(PLACE["last"])
        if 5 * k < n:
            f.append(PLACE["early"])
        if 5 * k >= 4 * n:
            f.append(PLACE["late"])
        f.append(PLACE["bias"])
        out.append(f)
    return out


@dataclass
class Field:
    """Weights of (feature, label) and (label, next label); label 1 is main text."""

    state: np.ndarray
    step: np.ndarray

    def decode(self, page: list[Block]) -> list[int]:
        """The most likely labels of a page's blocks (Viterbi)."""
        if not page:
            return []
        active = features(page)
        flat = np.fromiter((x for f in active for x in f), np.int64)
        first = np.cumsum([0, *map(len, active[:-1])])
        score = np.add.reduceat(self.state[flat], first, axis=0).tolist()
        (s00, s01), (s10, s11) = self.step.tolist()
        a, b = score[0]
        back = []
        for x, y in score[1:]:
            f0, f1 = a + s00 >= b + s10, a + s01 >= b + s11
            back.append((0 if f0 else 1, 0 if f1 else 1))
            a, b = (a + s00 if f0 else b + s10) + x, (a + s01 if f1 else b + s11) + y
        labels = [0 if a >= b else 1]
        for step in reversed(back):
            labels.append(step[labels[-1]])
        return labels[::-1]


def train(pages: list[tuple[list[Block], list[int]]], rounds: int = 150, rate: float = 0.15, decay: float = 1e-3) -> Field:
    """Maximum likelihood with weight decay, by Adam on the exact gradient (forward and backward passes over all pages at once)."""
    pages = [p for p in pages if p[0]]
    long, count = max(len(p) for p, _ in pages), len(pages)
    x = np.zeros((count, long, len(NAMES)))
    y = np.zeros((count, long), np.int64)
    mask = np.zeros((count, long))
    for k, (page, labels) in enumerate(pages):
        for t, f in enumerate(features(page)):
            x[k, t, f] = 1
        y[k, : len(page)], mask[k, : len(page)] = labels, 1
    real = np.stack([(y == 0) * mask, (y == 1) * mask], axis=2)
    pair = mask[:, 1:] * mask[:, :-1]
    real_step = np.einsum("pta,ptb,pt->ab", real[:, :-1], real[:, 1:], pair)
    state, step = np.zeros((len(NAMES), 2)), np.zeros((2, 2))
    moment = [np.zeros_like(w) for w in (state, state, step, step)]
    for r in range(1, rounds + 1):
        e = x @ state
        ahead, behind = np.zeros_like(e), np.zeros_like(e)
        ahead[:, 0] = e[:, 0]
        for t in range(1, long):
            go = np.logaddexp(ahead[:, t - 1, 0, None] + step[0], ahead[:, t - 1, 1, None] + step[1]) + e[:, t]
            ahead[:, t] = np.where(mask[:, t, None] > 0, go, ahead[:, t - 1])
        for t in range(long - 2, -1, -1):
            back = behind[:, t + 1] + e[:, t + 1]
            go = np.logaddexp(back[:, 0, None] + step[:, 0], back[:, 1, None] + step[:, 1])
            behind[:, t] = np.where(mask[:, t + 1, None] > 0, go, 0)
        whole = np.logaddexp(ahead[:, -1, 0], ahead[:, -1, 1])
        chance = np.exp(ahead + behind - whole[:, None, None]) * mask[:, :, None]
        joint = np.exp(ahead[:, :-1, :, None] + step + (e + behind)[:, 1:, None, :] - whole[:, None, None, None]) * pair[:, :, None, None]
        grads = (np.einsum("ptf,pta->fa", x, real - chance) / count - decay * state, (real_step - joint.sum(axis=(0, 1))) / count - decay * step)
        for k, (w, g) in enumerate(zip((state, step), grads, strict=True)):
            moment[2 * k] = 0.9 * moment[2 * k] + 0.1 * g
            moment[2 * k + 1] = 0.999 * moment[2 * k + 1] + 0.001 * g * g
            w += rate * (moment[2 * k] / (1 - 0.9**r)) / (np.sqrt(moment[2 * k + 1] / (1 - 0.999**r)) + 1e-8)
    return Field(state, step)


@lru_cache(maxsize=2)
def standard_field(n_pages: int = 600, seed: int = 11) -> Field:
    """The field trained on the labelled pages of page_samples; trained anew where it is needed first."""
    from pqspark.llm.page_samples import labelled_pages

    return train(labelled_pages(n_pages, seed))


def main_text(page: str | None, field: Field) -> str:
    found = leaf_blocks(page)
    return "\n\n".join(b.text for b, label in zip(found, field.decode(found), strict=True) if label)


def extracted(pages: DataFrame, field: Field | None = None) -> DataFrame:
    """(page_id, url, text, n_chars): the main text of every page.

    Blocks are joined in page order by a blank line.  A null or empty page, or
    one without main text, has the empty text.  Other columns are not read, null
    numbers and URLs pass through, repeated rows are treated alike, and an empty
    table gives an empty one.  Pages of any length and depth take time in
    proportion to their length.
    """
    field = field or standard_field()
    lean_batches(pages.sparkSession)

    def rows(batches):
        for batch in batches:
            texts = [main_text(p, field) for p in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).mapInArrow(rows, "page_id long, url string, text string, n_chars long")
