"""Toxicity by a learned lexicon, Levenshtein automata and context windows.

The lexicon (whole words, and stems that many endings follow) is learned from
labelled documents and kept as a trie.  The trie is intersected with the
Levenshtein automaton of a small distance into one deterministic automaton, so
that exact and misspelled terms are found in one walk over a word's letters and
most words end the walk after a few of them.  Each hit is then read in a window
of words: quotation marks and words of reporting around it count towards
quotation, words of address towards abuse.  A logistic model, fitted on the same
labelled documents, weighs hits by kind.
"""

from __future__ import annotations

import heapq
import math
import re
from bisect import bisect_left
from collections import Counter, defaultdict
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pqspark.llm.common import lean_batches, release_memory, stored
from pqspark.llm.shingles import shingle_sets

#: Labelled documents that the model is fitted on, at most (those with the smallest hash of their number).
FIT_ROWS = 24_000
#: Words on either side of a hit that its window holds.
WINDOW = 6
#: Entries (and their letters) that a task counts, and words whose matches it remembers, before it starts anew.
ENTRIES_HELD, LETTERS_HELD, WORDS_HELD = 60_000, 8_000_000, 100_000
WORD = re.compile(r"[\w*@$]+")
QUOTE = re.compile("[\"“”„«»‘`]")
#: Marks that are put around a term to disguise it.
MARKS = "*@$"
#: End of an entry that is a stem; no word holds it.
STEM = "~"
# Words that report speech, and words that address someone, in the four languages of the tables.
REPORTING = frozenset("said says say saying wrote writes called calls quote quoted quotes word words term terms dijo dice llamó palabra dit dites écrit appelé mot sagte sagt schrieb nannte wort zitat".split())
ADDRESS = frozenset("you your yours youre u ur tu tus te eres usted vous votre toi ton es du dein deine dich ihr euch bist".split())
# Fixed order of the features
FEATURES = ("bias", "word", "stem", "misspelled", "quoted", "reported", "addressed", "second_hit", "dense")


def _features_of(word: str) -> list[str]:
    """The lexicon entries that a word can support: itself, and stems of it written with a mark at the end."""
    return [word, *(word[:k] + STEM for k in range(4, min(len(word), 9)))]


def _count_rows(batches):
    """Entry, toxic and clean documents with it, and toxic words that begin with it, as partial counts of bounded size."""
    toxic, clean, endings = Counter(), Counter(), defaultdict(set)
    letters = 0

    def flushed():
        nonlocal letters
        letters = 0
        entries = list(toxic.keys() | clean.keys())
        columns = [pa.array(entries, pa.string()), *(pa.array([c[e] for e in entries], pa.int64()) for c in (toxic, clean)), pa.array([len(endings.get(e, ())) for e in entries], pa.int64())]
        for held in (toxic, clean, endings):
            held.clear()
        return pa.RecordBatch.from_arrays(columns, names=["entry", "toxic", "clean", "endings"])

    for batch in batches:
        for text, label in zip(batch.column("text"), batch.column("toxic").to_pylist(), strict=True):
            found = set()
            for word in set(WORD.findall((text.as_py() or "").lower())):
                if len(word) > 2:
                    entries = _features_of(word)
                    found.update(entries)
                    letters += len(word) * (word not in toxic and word not in clean)
                    if label:
                        for entry in entries[1:]:
                            if len(endings[entry]) < 8:
                                endings[entry].add(word)
            (toxic if label else clean).update(found)
            if len(toxic) + len(clean) > ENTRIES_HELD or letters > LETTERS_HELD:
                yield flushed()
    yield flushed()
    release_memory()


def lexicon(labelled: DataFrame, least: int = 3, purity: float = 0.9) -> dict[str, float]:
    """Entries (stems end in STEM) with the smoothed log-odds of a document that holds them.

    Candidates are entries that at least least toxic documents of
    labelled(text, toxic) hold, toxic ones being purity or more of all that hold
    them; a stem also needs several endings.  From these a cover is chosen:
    always the entry that explains most toxic documents no chosen entry has
    explained, by count times log-odds, and of equal ones the longest.  So a
    harmless word that came along with a toxic one a few times is left out.
    An entry held often enough for its share of toxic documents to be purity or
    more for certain (the lower Wilson bound) stays whatever it came along with,
    unless its own stems or endings among the chosen explain it.  What the driver
    holds is bounded by the labelled rows, which fit() bounds.
    """
    counts = labelled.mapInArrow(_count_rows, "entry string, toxic long, clean long, endings long")
    n, stem = F.col("toxic") + F.col("clean"), F.col("entry").endswith(STEM)
    told = counts.groupBy("entry").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"), F.max("endings").alias("endings"))
    kept = told.filter((F.col("toxic") >= least) & (F.col("toxic") >= purity * n) & (~stem | (F.col("endings") >= 2))).orderBy("entry").collect()
    strong = [r.entry for r in kept if wilson(r.toxic, r.toxic + r.clean) >= purity]
    odds = {r.entry: min(5.0, math.log((r.toxic + 0.5) / (r.clean + 0.5))) for r in kept}
    holding: dict[str, set[int]] = {e: set() for e in odds}
    for k, row in enumerate(labelled.filter("toxic > 0").mapInArrow(_held_rows(frozenset(odds)), "entries array<string>").toLocalIterator()):
        for entry in row.entries:
            holding[entry].add(k)
    chosen = cover(holding, odds, least)
    # chosen entries by their first letters, so that stems and endings are found without comparing all
    kin: dict[str, list[str]] = defaultdict(list)

    def enter(entry: str) -> None:
        chosen[entry] = odds[entry]
        bare = entry.rstrip(STEM)
        for k in range(4, min(len(bare), 9) + 1):
            kin[bare[:k]].append(entry)

    for entry in list(chosen):
        enter(entry)
    for entry in sorted(strong, key=lambda e: (len(holding[e]) * odds[e], len(e), e), reverse=True):
        if entry in chosen:
            continue
        bare = entry.rstrip(STEM)
        of_stems = {bare[:k] + STEM for k in range(4, min(len(bare), 9) + 1)} & chosen.keys()
        of_endings = kin.get(bare[:9], ()) if entry.endswith(STEM) else ()
        if len(holding[entry].difference(*(holding[c] for c in {*of_stems, *of_endings}))) >= least:
            enter(entry)
    return chosen


def cover(holding: dict[str, set[int]], odds: dict[str, float], least: int) -> dict[str, float]:
    """Entries in the order of what each explains beyond those before it, while that is least documents or more.

    An entry explains the less the more are chosen, so an old value is an upper
    bound, and only the entry at the top of the heap has to be looked at again.
    """
    heap = [(-len(held) * odds[e], -len(e), e, len(held)) for e, held in holding.items() if len(held) >= least]
    heapq.heapify(heap)
    chosen: dict[str, float] = {}
    explained: set[int] = set()
    while heap:
        _, _, entry, then = heapq.heappop(heap)
        left = len(holding[entry] - explained)
        if left == then:
            chosen[entry] = odds[entry]
            explained |= holding[entry]
        elif left >= least:
            heapq.heappush(heap, (-left * odds[entry], -len(entry), entry, left))
    return chosen


def wilson(hits: int, n: int, z: float = 2.0) -> float:
    """The lower bound of the share that hits of n stand for, by z standard errors."""
    p = hits / n
    return (p + z * z / (2 * n) - z * math.sqrt(p * (1 - p) / n + z * z / (4 * n * n))) / (1 + z * z / n)


def _held_rows(entries: frozenset[str]):
    def rows(batches):
        for batch in batches:
            found = []
            for text in batch.column("text").to_pylist():
                words = set(WORD.findall((text or "").lower()))
                found.append(sorted({e for w in words if len(w) > 2 for e in _features_of(w)} & entries))
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.list_(pa.string()))], names=["entries"])

    return rows


def distance_for(length: int) -> int:
    """Errors allowed in a term: none in short ones, one from five letters, two from nine."""
    return 0 if length < 5 else 1 if length < 9 else 2


class Automaton:
    """The lexicon trie intersected with Levenshtein automata, made deterministic as it is walked.

    A state is the set of (trie node, errors so far) that the letters read can
    have led to.  A node is only entered with as many errors as some term below
    it allows, so hopeless states are empty and the walk stops.
    """

    def __init__(self, entries: dict[str, float]):
        self.entries = entries
        self.child: list[dict[str, int]] = [{}]
        self.term: list[str | None] = [None]
        self.stem: list[str | None] = [None]
        self.allow = [0]
        for entry in entries:
            word, is_stem = entry.rstrip(STEM), entry.endswith(STEM)
            bound, at, path = (0 if is_stem else distance_for(len(word))), 0, [0]
            for c in word:
                if c not in self.child[at]:
                    self.child[at][c] = len(self.child)
                    self.child.append({})
                    self.term.append(None)
                    self.stem.append(None)
                    self.allow.append(0)
                at = self.child[at][c]
                path.append(at)
            for node in path:
                self.allow[node] = max(self.allow[node], bound)
            if is_stem:
                self.stem[at] = entry
            else:
                self.term[at] = entry
        self.letters = frozenset(c for kids in self.child for c in kids)
        self.states: list[tuple] = []
        self.next: list[dict[str, int]] = []
        self.found: list[tuple[str, int] | None] = []
        self.certain: list[str | None] = []
        self.known: dict[tuple, int] = {}
        self.start = self._state({0: 0})

    def _state(self, costs: dict[int, int]) -> int:
        """costs: errors by node; insertions of term letters are followed to their end."""
        reach, queue = {n: e for n, e in costs.items() if e <= self.allow[n]}, list(costs.items())
        while queue:
            node, errors = queue.pop()
            if reach.get(node, 99) < errors:
                continue
            for kid in self.child[node].values():
                if errors + 1 <= self.allow[kid] and reach.get(kid, 99) > errors + 1:
                    reach[kid] = errors + 1
                    queue.append((kid, errors + 1))
        if not reach:
            return -1
        key = tuple(sorted(reach.items()))
        if key not in self.known:
            self.known[key] = len(self.states)
            self.states.append(key)
            self.next.append({})
            ends = [(e, self.term[n]) for n, e in key if self.term[n] and e <= distance_for(len(self.term[n]))]
            self.found.append(min(ends)[::-1] if ends else None)
            self.certain.append(next((self.stem[n] for n, e in key if e == 0 and self.stem[n]), None))
        return self.known[key]

    def _step(self, state: int, letter: str) -> int:
        costs: dict[int, int] = {}
        for node, errors in self.states[state]:
            kid = self.child[node].get(letter)
            if kid is not None:
                costs[kid] = min(costs.get(kid, 99), errors)
            if errors < self.allow[node]:
                costs[node] = min(costs.get(node, 99), errors + 1)
            for other in self.child[node].values():
                if errors < self.allow[other]:
                    costs[other] = min(costs.get(other, 99), errors + 1)
        return self._state(costs)

    def match(self, word: str) -> tuple[str, int] | None:
        """(entry, errors) of the best match, exact ones first; None for nearly all words."""
        state, stem, letters, step = self.start, None, self.letters, self.next
        for c in word:
            if c not in letters:
                c = ""
            to = step[state].get(c)
            if to is None:
                to = step[state][c] = self._step(state, c)
            if to < 0:
                return (stem, 0) if stem else None
            state = to
            stem = stem or self.certain[state]
        hit = self.found[state]
        if stem and (hit is None or hit[1]):
            return stem, 0
        return hit


@dataclass
class Model:
    entries: dict[str, float]
    weights: list[float] = field(default_factory=lambda: [-2.0] + [0.0] * (len(FEATURES) - 1))

    def scorer(self):
        return Scorer(self)


class Scorer:
    """A model ready to read texts; one per task."""

    def __init__(self, model: Model):
        self.model, self.automaton = model, Automaton(model.entries)
        self.memo: dict[str, tuple[str, int] | None] = {}

    def entry(self, word: str) -> tuple[str, int] | None:
        """(entry, errors) of a word, also where marks are put around it; remembered."""
        if word in self.memo:
            return self.memo[word]
        if len(self.memo) > WORDS_HELD:
            self.memo.clear()
        got = self.automaton.match(word)
        if (got is None or got[1]) and (bare := word.strip(MARKS)) != word and bare:
            got = min((g for g in (got, self.automaton.match(bare)) if g), key=lambda g: g[1], default=None)
        if len(word) < 100:
            self.memo[word] = got
        return got

    def hits(self, text: str) -> tuple[list[re.Match], list[tuple[int, tuple[str, int]]]]:
        """The words of the text in lower case, and (number of the word, (entry, errors)) of each lexicon hit; no words where nothing is hit."""
        hot = {word: got for word in set(WORD.findall(text)) if (got := self.entry(word))}
        if not hot:
            return [], []
        words = list(WORD.finditer(text))
        return words, [(k, hot[w]) for k, m in enumerate(words) if (w := m.group()) in hot]

    def features(self, text: str | None) -> list[float]:
        """Kinds of hits, and what stands around them: in the whole line for quotation, in WINDOW words on either side for the rest."""
        text = (text or "").lower()
        words, found = self.hits(text)
        out = dict.fromkeys(FEATURES, 0.0)
        out["bias"] = 1.0
        marks = [m.start() for m in QUOTE.finditer(text)] if found else []
        line, line_end = 0, -1
        for k, (entry, errors) in found:
            kind = "misspelled" if errors else "stem" if entry.endswith(STEM) else "word"
            weight = self.model.entries[entry] / (1 + errors)
            start, end = words[k].span()
            if start > line_end:
                line, line_end = text.rfind("\n", 0, start) + 1, text.find("\n", end)
                line_end = len(text) if line_end < 0 else line_end
            near = {m.group() for m in (*words[max(0, k - WINDOW) : k], *words[k + 1 : k + 1 + WINDOW])}
            at = bisect_left(marks, start)
            out["quoted"] += (at - bisect_left(marks, line)) % 2 == 1 and at < len(marks) and marks[at] < line_end
            out["reported"] += not near.isdisjoint(REPORTING)
            out["addressed"] += not near.isdisjoint(ADDRESS)
            out[kind] = max(out[kind], weight)
        out["second_hit"] = float(len({e for _, (e, _) in found}) > 1)
        out["dense"] = min(1.0, 20 * len(found) / (1 + len(text) / 6))
        for name in ("quoted", "reported", "addressed"):
            out[name] /= max(1, len(found))
        return [out[name] for name in FEATURES]

    def score(self, text: str | None) -> float:
        z = sum(w * x for w, x in zip(self.model.weights, self.features(text), strict=True))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


#: What the weights are drawn to where the labelled documents say nothing, and how strongly.
PRIOR = np.array([-2.5, 1.0, 1.0, 0.8, -2.0, -0.5, 0.3, 0.5, 0.5])
STRENGTH = np.array([1.0, 1.0, 1.0, 2.0, 2.0, 2.0, 2.0, 2.0, 2.0])


def _feature_rows(model: Model):
    def rows(batches):
        scorer = model.scorer()
        for batch in batches:
            made = [scorer.features(t) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(made, pa.list_(pa.float64())), batch.column("toxic").cast(pa.int64())], names=["x", "toxic"])

    return rows


def _like_rows(batches):
    """Adds the least hash of a text's shingles of five words: near copies mostly share it, other texts hardly ever."""
    for batch in batches:
        like = [int(s[0].astype(np.int64)) if len(s) else 0 for s in shingle_sets(batch.column("text"), 5)]
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(like, pa.int64())], names=[*batch.schema.names, "like"])


def fit(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS) -> Model:
    """Learn lexicon and weights from docs(doc_id, text) joined with labels(doc_id, toxic).

    Labels are learned from only where crc32(doc_id as text) mod 5 is not 0, and
    from at most fit_rows such documents, of which near copies count once: all
    words of a text that was copied would look as toxic as its worst.  Rows whose number or label is null
    take no part; contradicting labels of one document count once each.  With no
    labelled rows the lexicon is empty and every text scores low.
    """
    lean_batches(docs.sparkSession)
    usable = labels.filter("doc_id is not null and toxic is not null and pmod(crc32(cast(doc_id as string)), 5) <> 0")
    chosen = usable.select(F.col("doc_id").cast("long").alias("doc_id"), "toxic").orderBy(F.xxhash64("doc_id"), "doc_id", "toxic").limit(fit_rows)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    labelled = texts.join(F.broadcast(chosen), "doc_id").select("text", F.col("toxic").cast("int").alias("toxic"))  # fit_rows bounds it
    labelled = stored(labelled.mapInArrow(_like_rows, "text string, toxic int, like long").dropDuplicates(["like", "toxic"]).select("text", "toxic"), "labelled")
    model = Model(lexicon(labelled))
    got = labelled.mapInArrow(_feature_rows(model), "x array<double>, toxic long").groupBy("x", "toxic").count().collect()
    if got:
        got.sort(key=lambda r: (r.x, r.toxic))  # the same sums in every run
        model.weights = logistic(np.array([r.x for r in got]), np.array([float(r.toxic > 0) for r in got]), np.array([float(r["count"]) for r in got])).tolist()
    return model


def logistic(x: np.ndarray, y: np.ndarray, n: np.ndarray, steps: int = 60) -> np.ndarray:
    """Newton's method, with halved steps where needed, for a logistic model on n[k] copies of row k, whose weights have normal priors."""

    def loss(w: np.ndarray) -> float:
        z = x @ w
        return float((n * (np.logaddexp(0, z) - y * z)).sum() + 0.5 * (STRENGTH * (w - PRIOR) ** 2).sum())

    w = PRIOR.copy()
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (n * (p - y)) + STRENGTH * (w - PRIOR)
        hess = (x * (n * p * (1 - p))[:, None]).T @ x + np.diag(STRENGTH)
        step, now = np.linalg.solve(hess, grad), loss(w)
        while np.abs(step).max() > 1e-9 and loss(w - step) > now:
            step = step / 2
        w = w - step
        if np.abs(step).max() < 1e-8:
            break
    return w


def _score_rows(model: Model):
    def rows(batches):
        scorer = model.scorer()
        for batch in batches:
            scores = [scorer.score(t) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(scores, pa.float64())], names=[*batch.schema.names[:-1], "score"])

    return rows


def scored(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every row of docs, from its whole text.

    A null text counts as empty and scores low; a null doc_id stays null and
    counts as held out.  Repeated rows give repeated, equal results.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_score_rows(model), "doc_id long, score double")
    held = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) == 0, F.lit(True))
    return rows.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def kept(docs: DataFrame, model: Model) -> DataFrame:
    """docs without the rows whose text scores 0.5 or more; columns, other rows and repeats as they were."""

    def rows(batches):
        scorer = model.scorer()
        for batch in batches:
            at = batch.schema.get_field_index("text")
            keep = [scorer.score(t) < 0.5 for t in batch.column(at).to_pylist()]
            yield batch.filter(pa.array(keep, pa.bool_()))
        del scorer
        release_memory()

    return docs.mapInArrow(rows, docs.schema)
