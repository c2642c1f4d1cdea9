"""Block kernels: a block of rows and a model to codes, in numpy.

All variants give the same codes.  They differ in the score that ranks the
centroids, in the order in which rows and chunks are visited, and in what they
keep: the staged form keeps the running minimum of a tile and nothing else.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from pqspark.model import PQModel

SCORES = ("full", "expanded", "ranking", "ranking2")
ORDERS = ("block_chunk", "row_major", "subspace_major")
#: Rows that the row-major order takes through all chunks at a time.
ROW_RUN = 16
#: Bytes of score tables that the matrix form holds at a time.
TABLE_BYTES = 1 << 25
#: 32-bit scores that a tile holds at a time (half a megabyte, within a core's cache).
TILE_SCORES = 1 << 17


def piece(x: np.ndarray, model: PQModel, j: int) -> np.ndarray:
    lo, hi = model.offsets[j], model.offsets[j + 1]
    out = x[:, lo : min(hi, x.shape[1])]
    if hi > x.shape[1]:
        out = np.pad(out, ((0, 0), (0, hi - x.shape[1])))
    return np.ascontiguousarray(out)


def scores(p: np.ndarray, lanes: np.ndarray, bias: np.ndarray, score: str, accumulate: str, out: np.ndarray | None = None) -> np.ndarray:
    """[rows, centroids] of a tile, into out if given.  fma walks the dimensions one by one, gemm takes one product; full is always stepwise."""
    if out is None:
        out = np.empty((len(p), lanes.shape[1]), p.dtype)
    if score == "full":
        out.fill(0)
        gap = np.empty_like(out)
        for d in range(lanes.shape[0]):
            np.subtract(p[:, d, None], lanes[d], out=gap)
            np.multiply(gap, gap, out=gap)
            out += gap
        return out
    if accumulate == "gemm":
        np.matmul(p, lanes, out=out)
    else:
        out.fill(0)
        for d in range(lanes.shape[0]):
            out += p[:, d, None] * lanes[d]
    if score == "ranking":
        np.subtract(bias, out, out=out)
    elif score == "ranking2":
        out *= -2
        out += 2 * bias
    elif score == "expanded":
        out *= -2
        out += 2 * bias
        out += (p * p).sum(axis=1)[:, None]
    else:
        raise ValueError(f"score must be one of {SCORES}")
    return out


def tiled(p: np.ndarray, lanes: np.ndarray, bias: np.ndarray, tile: int, score: str, accumulate: str) -> np.ndarray:
    """The winner of each row; tiles go upward and only a strictly smaller score replaces, so ties keep the smaller number."""
    k = lanes.shape[1]
    if tile >= k:
        return scores(p, lanes, bias, score, accumulate).argmin(axis=1)
    best, arg = np.full(len(p), np.inf, p.dtype), np.zeros(len(p), np.int64)
    buffer = np.empty((len(p), tile), p.dtype)
    for lo in range(0, k, tile):
        part = np.ascontiguousarray(lanes[:, lo : lo + tile])
        got = scores(p, part, bias[lo : lo + tile], score, accumulate, buffer[:, : part.shape[1]] if part.shape[1] == tile else None)
        at = got.argmin(axis=1)
        low = got[np.arange(len(p)), at]
        less = low < best
        best[less], arg[less] = low[less], lo + at[less]
    return arg


def _prepared(model: PQModel, dtype, center: bool) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(lanes, bias, mean) by chunk; centring moves rows and centroids by the chunk's mean, which leaves the winner.  Kept with the model."""
    key = (np.dtype(dtype).str, center)
    if key not in model.tables:
        out = []
        for lanes, bias, book in zip(model.lanes, model.bias, model.books, strict=True):
            mean = book.mean(axis=0) if center else np.zeros(book.shape[1])
            if center:
                moved = book - mean
                lanes, bias = np.ascontiguousarray(moved.T), 0.5 * (moved * moved).sum(axis=1)
            out.append((lanes.astype(dtype), bias.astype(dtype), mean))
        model.tables[key] = out
    return model.tables[key]


@dataclass
class Ranked:
    """A chunk's codebook for ranking by one product of 32-bit floats: rows with a one behind them times the negated lanes over the biases."""

    mean: np.ndarray
    factors: np.ndarray  # [width + 1, k]
    book: np.ndarray
    bias: np.ndarray
    reach: float  # the longest centroid from the mean
    least: float  # the greatest bias that ranks


def _ranked(model: PQModel) -> list[Ranked]:
    if "ranked" not in model.tables:
        out = []
        for book in model.books:
            mean = book.mean(axis=0)
            moved = book - mean
            bias = 0.5 * (moved * moved).sum(axis=1)
            _, first = np.unique(book, axis=0, return_index=True)
            again = np.ones(len(book), bool)
            again[first] = False  # a centroid that is there already never wins, since ties go to the smaller number
            factors = np.concatenate([-moved.T, np.where(again, 0.0, bias)[None]]).astype(np.float32)
            factors[:, again] = np.r_[np.zeros(book.shape[1]), 1e38][:, None]  # beyond any score, and finite for the product
            out.append(Ranked(mean, np.ascontiguousarray(factors), book, np.where(again, np.inf, 0.5 * (book * book).sum(axis=1)), float(np.sqrt(2 * bias.max())), float(bias.max())))
        model.tables["ranked"] = out
    return model.tables["ranked"]


#: Unit of rounding of 32-bit floats.
ROUNDING = 2.0**-24


def ranked(p: np.ndarray, table: Ranked, work: dict) -> np.ndarray:
    """The winners of a tile by 32-bit scores; rows whose two best scores lie within the rounding error are ranked again in 64 bits.

    The error of a score is below (width + 4) roundings of |row| * |centroid| and
    the bias, both taken from the centroids' mean; two scores err twice.
    """
    n, width = p.shape
    k = table.factors.shape[1]
    if work.get("shape") != (n, width, k):
        work |= {"shape": (n, width, k), "rows": np.ones((n, width + 1), np.float32), "scores": np.empty((n, k), np.float32), "at": np.arange(n)}
    rows, scores_, at = work["rows"], work["scores"], work["at"]
    np.subtract(p, table.mean, out=rows[:, :width], casting="unsafe")
    np.matmul(rows, table.factors, out=scores_)
    won = scores_.argmin(axis=1)
    if k == 1:
        return won
    low = scores_[at, won]
    scores_[at, won] = np.inf
    gap = scores_.min(axis=1) - low
    length = np.sqrt(np.einsum("rd,rd->r", rows[:, :width], rows[:, :width]).astype(np.float64))
    close = np.flatnonzero(~(gap > 2 * (width + 4) * ROUNDING * (length * table.reach + table.least)))
    if len(close):
        won[close] = (table.bias - p[close] @ table.book.T).argmin(axis=1)
    return won


#: Numbers that one operation of the form by dimensions runs over without a break, and differences that it holds at a time.
RUN, GAPS = 256, 1 << 16


class _Wide:
    """Rows' pieces against a codebook, dimensions innermost: eight of them (or all) side by side, and so for many centroids in a row.

    Squares are added up in numpy's own order of a sum along a row, whatever
    the row, so that equal centroids keep equal distances.
    """

    def __init__(self, p: np.ndarray, book: np.ndarray):
        self.k, width = book.shape
        self.part = 8 if width in (8, 16) else width
        groups = width // self.part
        times = max(1, min(self.k, RUN // self.part))
        filled = -(-self.k // times) * times
        book = np.concatenate([book, book[: filled - self.k]]).reshape(filled, groups, self.part).transpose(1, 0, 2)
        self.book = np.ascontiguousarray(book).reshape(groups, filled // times, times * self.part)
        self.p = p.reshape(len(p), groups, self.part)
        self.step = max(1, min(ROW_RUN, GAPS // self.book.size))
        self.own = np.empty((self.step, groups, times, self.part), p.dtype)
        self.gap = np.empty((self.step, *self.book.shape), np.result_type(p, book))

    def winners(self, a: int, b: int) -> np.ndarray:
        found = []
        for at in range(a, b, self.step):
            p = self.p[at : min(at + self.step, b)]
            own, gap = self.own[: len(p)], self.gap[: len(p)]
            own[:] = p[:, :, None, :]
            np.subtract(own.reshape(len(p), len(self.book), 1, -1), self.book, out=gap)
            np.multiply(gap, gap, out=gap)
            found.append(self._total(gap).reshape(len(p), -1)[:, : self.k].argmin(axis=1))
        return np.concatenate(found)

    def _total(self, squares: np.ndarray) -> np.ndarray:
        total = squares[:, 0]
        for g in range(1, squares.shape[1]):
            total = np.add(total, squares[:, g], out=squares[:, 0])
        if self.part > 8:
            return total.reshape(-1, self.part).sum(axis=1)
        if self.part < 8:
            parts = total.reshape(-1, self.part)
            total = parts[:, 0]
            for d in range(1, self.part):
                total = total + parts[:, d]
            return total
        total = total.reshape(-1)
        for _ in range(3):
            total = total[0::2] + total[1::2]
        return total


def encode(
    x: np.ndarray,
    model: PQModel,
    strategy: str = "staged",
    score: str | None = None,
    order: str | None = None,
    block_rows: int = 2048,
    tile: int | None = None,
    accumulate: str = "gemm",
    precision: str = "checked",
    center: str = "auto",
) -> np.ndarray:
    """Codes [rows, chunks] of finite rows x, as int16 where they fit and int32 beyond.

    precision: checked ranks in 32-bit floats and settles near ties in 64 (staged
    only; other strategies then take 64); f64; or f32, unchecked.
    """
    m = model.chunks
    out = np.zeros((len(x), m), np.int16 if model.k <= 1 << 15 else np.int32)
    if strategy == "staged" and precision == "checked" and score is None and tile is None and order in (None, "block_chunk") and accumulate == "gemm" and center == "auto" and 1e-16 < model.spread < 1e16:
        step, work = max(64, min(block_rows, TILE_SCORES // model.k)), {}
        chunks = _ranked(model)
        for a in range(0, len(x), step):
            block = x[a : a + step]
            top = np.abs(block).max(initial=0.0)
            if top < 1e16:
                for j in range(m):
                    out[a : a + step, j] = ranked(piece(block, model, j), chunks[j], work)
            else:
                out[a : a + step] = encode(block, model, "staged", precision="f64")
        return out
    dtype = np.float32 if precision == "f32" else np.float64
    tables = _prepared(model, dtype, center == "on" or center == "auto" and precision == "f32")

    def cut(rows: np.ndarray, j: int) -> np.ndarray:
        p, mean = piece(rows, model, j), tables[j][2]
        return (p - mean if mean.any() else p).astype(dtype)

    if strategy == "rowwise":
        for i in range(len(x)):
            for j in range(m):
                gap = model.books[j] - piece(x[i : i + 1], model, j)
                out[i, j] = (gap * gap).sum(axis=1).argmin()
        return out
    if strategy == "lane_by_dimension":
        # rows in turn through all chunks, differences to every centroid, sums over the few dimensions of a piece
        wides = [_Wide(piece(x, model, j), book) for j, book in enumerate(model.books)]
        for a in range(0, len(x), ROW_RUN):
            for j, wide in enumerate(wides):
                out[a : a + ROW_RUN, j] = wide.winners(a, min(a + ROW_RUN, len(x)))
        return out
    if strategy == "matrix":
        # whole tables of scores first, then one reduction over each; a block of rows at a time, so that tables of large batches fit
        step = max(ROW_RUN, TABLE_BYTES // (m * model.k * np.dtype(dtype).itemsize))
        kept = [np.empty((min(step, len(x)), table[0].shape[1]), dtype) for table in tables]
        for a in range(0, len(x), step):
            for j in range(m):
                p = cut(x[a : a + step], j)
                scores(p, tables[j][0], tables[j][1], score or "expanded", accumulate, kept[j][: len(p)])
            for j, table in enumerate(kept):
                out[a : a + step, j] = table[: len(x[a : a + step])].argmin(axis=1)
        return out
    if strategy == "expanded":
        score, order, tile, keep = score or "expanded", order or "row_major", tile or model.k, True
    elif strategy in ("staged", "tiled"):
        score, order, tile, keep = score or "ranking", order or "block_chunk", tile or model.k, False
    else:
        raise ValueError(f"no strategy {strategy}")
    if order not in ORDERS:
        raise ValueError(f"order must be one of {ORDERS}")

    cuts = [cut(x, j) for j in range(m)] if order == "row_major" else None  # once, not for each short run
    kept = np.empty((ROW_RUN if cuts else block_rows, max(len(b) for b in model.books)), dtype) if keep else None

    def visit(rows: slice, j: int) -> None:
        p = cuts[j][rows] if cuts else cut(x[rows], j)
        if keep:
            lanes, bias = tables[j][:2]
            whole = kept if lanes.shape[1] == kept.shape[1] else np.empty((len(kept), lanes.shape[1]), dtype)
            out[rows, j] = scores(p, lanes, bias, score, accumulate, whole[: len(p)]).argmin(axis=1)
        else:
            out[rows, j] = tiled(p, tables[j][0], tables[j][1], tile, score, accumulate)

    runs = [slice(a, a + (ROW_RUN if order == "row_major" else block_rows)) for a in range(0, len(x), ROW_RUN if order == "row_major" else block_rows)]
    if order == "subspace_major":
        for j in range(m):
            for rows in runs:
                visit(rows, j)
    else:
        for rows in runs:
            for j in range(m):
                visit(rows, j)
    return out


def pack(codes: np.ndarray, bits: int) -> list[bytes]:
    """Codes of each row as bytes, bits for each, the first in the highest bits."""
    spread = (codes.astype(np.uint32)[:, :, None] >> np.arange(bits - 1, -1, -1)) & 1
    return [r.tobytes() for r in np.packbits(spread.reshape(len(codes), -1).astype(np.uint8), axis=1)]


def unpack(packed: list[bytes], chunks: int, bits: int) -> np.ndarray:
    raw = np.frombuffer(b"".join(packed), np.uint8).reshape(len(packed), -1)
    spread = np.unpackbits(raw, axis=1)[:, : chunks * bits].reshape(len(packed), chunks, bits).astype(np.int32)
    return (spread << np.arange(bits - 1, -1, -1)).sum(axis=2).astype(np.int16 if bits < 16 else np.int32)
