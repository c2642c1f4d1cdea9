"""Vectorised word shingles: whole Arrow columns of text to 64-bit shingle sets.

Words are maximal runs of bytes other than 0x20 and 0x09-0x0D, after A-Z are
lower-cased; on UTF-8 this is exactly the character-level definition.  Word
hashes come from one running polynomial over the bytes (mod 2**64), so the cost
is a few array passes per byte and no Python object is made for a word.

Two unequal shingles of one *pair of documents* share a hash with probability
about n*m/2**64, which is below 1e-11 even for documents of a million words.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
_BASE, _MASK = 0x9E3779B97F4A7C55, (1 << 64) - 1
_INVERSE = pow(_BASE, -1, 1 << 64)
#: Bytes hashed at a time; slices end at white space, so a longer word makes a longer slice.
SLICE = 1 << 19

_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint64)
_LOWER[65:91] += U(32)
_LOWER += U(1)

_powers = (np.ones(1, np.uint64), np.ones(1, np.uint64))


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _powers
    if len(_powers[0]) < n:
        grown = []
        for base in (_BASE, _INVERSE):
            table = np.full(max(n, SLICE + 1), U(base), np.uint64)
            table[0] = U(1)
            grown.append(np.multiply.accumulate(table))
        _powers = (grown[0], grown[1])
    return _powers


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser with full avalanche (the public splitmix64 constants)."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary column; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    if offsets is None or len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    off = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, off - off[0]


def _word_slice(raw: np.ndarray, breaks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start positions and hashes of the words of raw; a word also ends before each position in breaks."""
    solid = ~_SPACE[raw]
    first = solid.copy()
    first[1:] &= ~solid[:-1]
    last = solid.copy()
    last[:-1] &= ~solid[1:]
    inner = breaks[(breaks > 0) & (breaks < len(raw))]
    first[inner] = solid[inner]
    last[inner - 1] = solid[inner - 1]
    start, end = np.flatnonzero(first), np.flatnonzero(last)
    up, down = _power_tables(len(raw) + 1)
    running = np.cumsum(_LOWER[raw] * up[: len(raw)], dtype=np.uint64)
    before = np.where(start > 0, running[start - 1], U(0))
    hashes = (running[end] - before) * down[start]
    return start, mix(hashes + (end - start + 1).astype(np.uint64) * U(0xD6E8FEB86659FD93))


def words(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(hash of each word, index of each text's first word with a final total)."""
    raw, off = text_bytes(column)
    starts, hashes, at = [], [], 0
    while at < len(raw):
        stop = at + SLICE
        if stop < len(raw):
            while stop < len(raw):
                gap = np.flatnonzero(_SPACE[raw[stop : stop + 4096]])
                if len(gap):
                    stop += int(gap[0])
                    break
                stop += 4096
            stop = min(stop, len(raw))
        else:
            stop = len(raw)
        lo, hi = np.searchsorted(off, [at, stop])
        s, h = _word_slice(raw[at:stop], off[lo:hi] - at)
        starts.append(s + at)
        hashes.append(h)
        at = stop
    if not starts:
        return np.zeros(0, np.uint64), np.zeros(len(off), np.int64)
    return np.concatenate(hashes), np.searchsorted(np.concatenate(starts), off)


def shingle_sets(column: pa.Array, width: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text.

    A text of 1 to width-1 words has one shingle, its whole sequence; a text
    without words has none.
    """
    hashes, first = words(column)
    weight = mix(np.arange(1, width + 1, dtype=np.uint64) * U(0xA0761D6478BD642F)) | U(1)
    if len(hashes) >= width:
        n = len(hashes) - width + 1
        rolled = hashes[:n] * weight[0]
        for j in range(1, width):
            rolled += hashes[j : n + j] * weight[j]
        rolled = mix(rolled)
    else:
        rolled = hashes[:0]
    for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        if b - a >= width:
            yield np.unique(rolled[a : b - width + 1])
        elif b > a:
            yield mix(np.array([(hashes[a:b] * weight[: b - a]).sum(dtype=np.uint64) ^ U(b - a)], np.uint64))
        else:
            yield hashes[:0]


def fingerprint(shingles: np.ndarray) -> int:
    """A signed 64-bit key of a whole set; equal sets have equal keys."""
    total = int(mix(shingles ^ U(0x2545F4914F6CDD1D)).sum(dtype=np.uint64)) + len(shingles) * _BASE
    return int(mix(np.array([total & _MASK], np.uint64)).view(np.int64)[0])


class Parts:
    """Signatures of which any two sets of enough similarity share one.

    Sets are put into size levels so that two sets with Jaccard >= num/den are
    in the same or in adjacent levels.  At a level the hash range is cut into
    differ + 1 + spare parts, where such a pair has at most differ shingles that
    are not in both, so that at least 1 + spare parts hold the same shingles in
    both; a part is signed by the sum of its members.  A set signs its
    differ + 1 strongest parts only: in an order that depends on a part's
    content alone, two sets that agree in 1 + spare of their parts agree in one
    of those.  Strong is what is seldom shared by chance: a part with many
    shingles outside common (sorted; which shingles are in it changes what is
    signed, but loses no pair), then one with many shingles.  Empty parts come last.

    A set signs at its own level and at the next; the lowest bit marks
    signatures at the own level (upper), and two sets that are similar enough
    share one, but for that bit, that is upper in at least one of them.

    With each signature goes a check: the parities, by 64 hashed classes, of the
    shingles in the run of RUN parts that it lies in.  Of the parts that two
    similar sets have alike, the strongest in a run with at most RUN - 1
    shingles of one set alone is signed by both: a run with more has at least as
    many such shingles as parts, so that at most differ parts come before.  Two
    sets whose checks differ in more bits than limit(signature) therefore need
    not be tied by that signature.
    """

    #: Spare parts for each part that is signed, at least.
    SPARE = 0.5
    #: Parts that one check covers.
    RUN = 8

    def __init__(self, num: int, den: int, common: np.ndarray | None = None):
        self.num, self.den = num, den
        self.common = common if common is not None and len(common) else None
        self.floor = [1]  # smallest size of each level
        self.edges: dict[int, tuple[np.ndarray, int]] = {}

    def level(self, size: int) -> int:
        while self.floor[-1] <= size:
            self.floor.append(max(self.floor[-1] + 1, (self.floor[-1] - 1) * self.den // self.num + 1))
        return int(np.searchsorted(self.floor, size, side="right")) - 1

    def _cut(self, level: int) -> tuple[np.ndarray, int]:
        """(inner bounds of the parts, number of parts signed; 0 if only equal sets are similar enough)."""
        if level not in self.edges:
            while len(self.floor) <= level + 1:
                self.level(self.floor[-1])
            top, low = self.floor[level + 1] - 1, self.floor[max(level - 1, 0)]
            differ = 2 * top * (self.den - self.num) // (self.den + self.num)
            signed = differ + 1 if differ else 0
            least = spare = int(np.ceil(self.SPARE * signed))
            if differ:
                for _ in range(8):
                    expect = (signed + spare) * np.exp(-low / (signed + spare))
                    spare = max(least, int(np.ceil(expect + 3 * np.sqrt(expect))))
            n = signed + spare
            self.edges[level] = (np.array([(k << 64) // n for k in range(1, n)], dtype=np.uint64), signed)
        return self.edges[level]

    @staticmethod
    def limit(signatures: np.ndarray) -> np.ndarray:
        """Bits in which the checks of a signature may differ between sets of enough similarity; held in the three bits above the lowest."""
        return (signatures >> U(1)) & U(7)

    def signatures(self, shingles: np.ndarray) -> np.ndarray:
        return self.checked(shingles)[0]

    def checked(self, shingles: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The signatures of a set, and the check of each."""
        n = len(shingles)
        if n == 0:
            return shingles, shingles
        own = self.level(n)
        running, parity, rare = np.zeros(n + 1, np.uint64), np.zeros(n + 1, np.uint64), np.arange(n + 1)
        mixed = mix(shingles)
        np.cumsum(mixed, dtype=np.uint64, out=running[1:])
        np.bitwise_xor.accumulate(U(1) << (mixed & U(63)), out=parity[1:])
        if self.common is not None:
            at = np.minimum(np.searchsorted(self.common, shingles), len(self.common) - 1)
            np.cumsum(self.common[at] != shingles, out=rare[1:])
        out, checks = [], []
        for level in (own, own + 1):
            edges, signed = self._cut(level)
            if not signed:
                continue
            bound = np.empty(len(edges) + 2, np.int64)
            bound[0], bound[-1] = 0, n
            bound[1:-1] = np.searchsorted(shingles, edges)
            total = running[bound[1:]] - running[bound[:-1]]
            part = np.arange(len(total), dtype=np.uint64)
            signs = mix(total + part * U(0xE7037ED1A0B428DB) + U((level + 1) * 0x8EBC6AF09C88C6E3 & _MASK)) & ~U(15)
            signs |= U(1 | min(self.RUN, signed) - 1 << 1)
            strong = np.lexsort((signs, -np.diff(bound), -np.diff(rare[bound])))[:signed]
            start = np.arange(0, len(total), self.RUN)
            check = parity[bound[np.minimum(start + self.RUN, len(total))]] ^ parity[bound[start]]
            out.append(signs[strong] if level == own else signs[strong] & ~U(1))
            checks.append(check[strong // self.RUN])
        return (np.concatenate(out), np.concatenate(checks)) if out else (shingles[:0], shingles[:0])
