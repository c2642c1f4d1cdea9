"""The analytic cost model: counted operations, score cells, live bytes and codebook switches, in closed form."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

STRATEGIES = ("lane_by_dimension", "matrix", "expanded", "tiled_full", "staged")


def counters(n: int, dim: int, chunks: int, k: int, strategy: str, block_rows: int = 2048, tile: int = 16, bits: int = 8) -> dict[str, int]:
    """Whole numbers for n rows; multiplications, additions and subtractions count one each."""
    ranked = n * k * (2 * dim - chunks)
    norms = n * (2 * dim - chunks)
    arithmetic = {
        "lane_by_dimension": n * k * 3 * dim - n * k * chunks,
        "matrix": norms + 3 * n * chunks * k + ranked,
        "expanded": norms + 3 * n * chunks * k + ranked,
        "tiled_full": n * k * 3 * dim - n * k * chunks,
        "staged": ranked + n * chunks * k,
    }[strategy]
    live = {"lane_by_dimension": 4 * k, "matrix": 4 * n * k, "expanded": 4 * block_rows * k, "tiled_full": 4 * block_rows * tile, "staged": 4 * block_rows * tile}[strategy]
    switches = {"lane_by_dimension": n * chunks, "matrix": chunks, "expanded": n * chunks, "tiled_full": -(-n // block_rows) * chunks, "staged": -(-n // block_rows) * chunks}[strategy]
    return {
        "arithmetic": arithmetic,
        "compares": n * chunks * (k - 1),
        "distances": n * chunks * k,
        "score_cells": 0 if strategy in ("tiled_full", "staged") else n * chunks * k,
        "live_score_bytes": live,
        "codebook_switches": switches,
        "bytes_in": 4 * n * dim,
        "bytes_out": n * -(-chunks * bits // 8),
        "codebook_bytes": 4 * k * (dim + chunks),
        "offline": 2 * k * dim,
        "transfer_bytes": n * (4 * dim + -(-chunks * bits // 8)),
    }


def model(spark: SparkSession, n: int, dim: int, chunks: int, k: int, strategies: tuple[str, ...] = STRATEGIES, **options) -> DataFrame:
    rows = [(s, name, int(value)) for s in strategies for name, value in counters(n, dim, chunks, k, s, **options).items()]
    return spark.createDataFrame(rows, "strategy string, counter string, value long")


def lane_use(width: int, lanes: int, k: int) -> tuple[float, float]:
    """Shares of lanes in use: over the dimensions of a piece, and over centroids."""
    return min(1.0, width / (lanes * -(-width // lanes))), k / (lanes * -(-k // lanes))


def lanes_used(shapes: list[tuple[int, int]], width: int, lanes: int, k: int) -> tuple[float, float]:
    """lane_use over all pieces of (dimensions, rows), the last of a vector as short as it is, and with no more centroids than rows."""
    used = sum(n * dim for dim, n in shapes)
    all_ = sum(n * lanes * (dim // width * -(-width // lanes) + -(-(dim % width) // lanes)) for dim, n in shapes)
    return used / all_, lane_use(width, lanes, min(k, sum(n for _, n in shapes)))[1]


def working_set(width: int, k: int) -> int:
    """Bytes of one chunk's codebook and biases as 32-bit floats."""
    return 4 * k * width + 4 * k


def sizes(dim: int, chunks: int, bits: int) -> tuple[int, int, float]:
    """(bits, bytes, compression against 32-bit floats) of a code."""
    return chunks * bits, -(-chunks * bits // 8), 32 * dim / (chunks * bits)


def choose(dim: int, k: int, width: int, python: bool = True) -> str:
    """A strategy from the shape alone: expressions for tiny models where Python is unwanted, else the staged kernel."""
    if python:
        return "staged"
    return "flat_expr" if k * dim <= 256 else "hof" if k * dim <= 16_384 else "relational"
