"""Functions for SQL users, bound to a model: pq_encode, pq_decode, the aggregate vector_mean and the table function pq_chunks."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from pqspark.functions import kernels
from pqspark.model import PQModel


def register(spark: SparkSession, model: PQModel) -> None:
    """Register pq_encode(vector) -> codes and pq_decode(codes) -> vector for this model; null in, null out.

    pq_chunks(vector) is a table of (chunk, code), without rows for null; use it as LATERAL pq_chunks(column).
    """

    @F.pandas_udf("array<smallint>")
    def pq_encode(v: pd.Series) -> pd.Series:
        out = pd.Series([None] * len(v), dtype=object)
        good = np.flatnonzero(v.notna().to_numpy())
        if len(good):
            codes = kernels.encode(np.stack(v.iloc[good].to_numpy()).astype(np.float64), model)
            for k, c in zip(good, codes, strict=True):
                out.iloc[k] = c.tolist()
        return out

    @F.pandas_udf("array<double>")
    def pq_decode(c: pd.Series) -> pd.Series:
        return c.map(lambda code: None if code is None else np.concatenate([b[k] for b, k in zip(model.books, code, strict=True)])[: model.config.dim].tolist())

    @F.pandas_udf("array<double>")
    def vector_mean(v: pd.Series) -> list:
        return np.stack(v.to_numpy()).astype(np.float64).mean(axis=0).tolist()

    class Chunks:
        def eval(self, v):
            if v is not None:
                yield from enumerate(kernels.encode(np.array([v], np.float64), model)[0].tolist())

    spark.udtf.register("pq_chunks", F.udtf(Chunks, returnType="chunk int, code int"))
    for name, f in (("pq_encode", pq_encode), ("pq_decode", pq_decode), ("vector_mean", vector_mean)):
        spark.udf.register(name, f)
