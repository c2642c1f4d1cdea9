"""Pieces of vectors, codebook layouts and packed codes, as DataFrame expressions."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pqspark.functions import kernels
from pqspark.model import PQConfig


def doubles(vector: str = "embedding") -> Column:
    return F.col(vector).cast("array<double>")


def pieces(config: PQConfig, vector: str = "embedding") -> list[Column]:
    """A slice per chunk; with split='pad' the last is filled with zeros."""
    v, off = doubles(vector), config.offsets()
    if config.split == "pad" and off[-1] > config.dim:
        v = F.concat(v, F.array_repeat(F.lit(0.0), off[-1] - config.dim))
    return [F.slice(v, a + 1, b - a) for a, b in zip(off[:-1], off[1:], strict=True)]


def split(df: DataFrame, config: PQConfig, layout: str = "rows", id_col: str = "vec_id", vector: str = "embedding", keep: tuple[str, ...] = ()) -> DataFrame:
    """rows: (id, chunk, sub); columns: (id, s0, s1, ...)."""
    cut = pieces(config, vector)
    if layout == "columns":
        return df.select(id_col, *keep, *(c.alias(f"s{j}") for j, c in enumerate(cut)))
    return df.select(id_col, *keep, F.posexplode(F.array(*cut)).alias("chunk", "sub"))


def subspace(df: DataFrame, config: PQConfig, j: int, id_col: str = "vec_id", vector: str = "embedding") -> DataFrame:
    return df.select(id_col, pieces(config, vector)[j].alias("sub"))


def dot(a: str | Column, b: str | Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def squared(a: str | Column, b: str | Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def with_bias(codebook: DataFrame) -> DataFrame:
    return codebook.withColumn("bias", dot("coords", "coords") / 2)


def to_lanes(codebook: DataFrame) -> DataFrame:
    """(chunk, dim, lane): all centroids of one dimension side by side."""
    each = codebook.select("chunk", "centroid", F.posexplode("coords").alias("dim", "x"))
    return each.groupBy("chunk", "dim").agg(F.transform(F.array_sort(F.collect_list(F.struct("centroid", "x"))), lambda s: s.x).alias("lane"))


def from_lanes(lanes: DataFrame) -> DataFrame:
    each = lanes.select("chunk", "dim", F.posexplode("lane").alias("centroid", "x"))
    return each.groupBy("chunk", "centroid").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "x"))), lambda s: s.x).alias("coords"))


def pad_tiles(lanes: DataFrame, bias: DataFrame, tile: int) -> tuple[DataFrame, DataFrame]:
    """Lanes filled with zeros, biases (chunk, biases) with infinity, to whole tiles; the filling never wins."""
    missing = lambda c: F.pmod(F.lit(tile) - F.pmod(F.size(c), F.lit(tile)), F.lit(tile))
    return (
        lanes.withColumn("lane", F.concat("lane", F.array_repeat(F.lit(0.0), missing("lane")))),
        bias.withColumn("biases", F.concat("biases", F.array_repeat(F.lit(float("inf")), missing("biases")))),
    )


def pack(df: DataFrame, bits: int, codes: str = "codes") -> DataFrame:
    """df with code, the packed form of its codes column (first code in the highest bits)."""

    @F.pandas_udf("binary")
    def packed(column):
        import numpy as np
        import pandas as pd

        return pd.Series(kernels.pack(np.stack(column.to_numpy()), bits) if len(column) else [])

    return df.withColumn("code", packed(codes))


def unpack(df: DataFrame, chunks: int, bits: int) -> DataFrame:
    @F.pandas_udf("array<smallint>")
    def unpacked(column):
        import pandas as pd

        return pd.Series(list(kernels.unpack(list(column), chunks, bits)) if len(column) else [])

    return df.withColumn("codes", unpacked("code"))


def pack_sql(codes: str = "codes", bits: int = 8) -> Column:
    """The packed form for 8 bits, JVM only."""
    if bits != 8:
        raise ValueError("only whole bytes; use pack()")
    return F.unhex(F.array_join(F.transform(codes, lambda c: F.lpad(F.hex(c.cast("long")), 2, "0")), ""))


def joined(codes: str = "codes") -> Column:
    """Codes as text, for comparisons."""
    return F.array_join(F.col(codes).cast("array<string>"), ",")


def write_by_chunk(df: DataFrame, config: PQConfig, path: str) -> None:
    """Pieces partitioned by chunk, for the subspace-major order: a job on one chunk reads only its folder."""
    split(df, config).write.mode("overwrite").partitionBy("chunk").parquet(path)


ARROW_FLOATS = pa.list_(pa.float32())
