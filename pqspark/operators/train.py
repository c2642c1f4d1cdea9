"""Codebook training: sampling, seeds, distributed and relational Lloyd iterations, refresh."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pqspark.functions import kernels
from pqspark.functions.arrow import matrix
from pqspark.model import PQConfig, PQModel
from pqspark.operators import encode as enc
from pqspark.operators import layout

#: Sums are taken in whole multiples of 1 / UNIT (or larger ones where the data would overflow), so that they do not depend on the order of addition.
UNIT = 1 << 24
#: Rows of a batch that are added up in floats at a time.
BATCH = 1 << 14


def _largest(batches):
    """(top, n): the largest finite component of a partition's vectors, whatever their length, and its rows."""
    top, n = 0.0, 0
    for batch in batches:
        x = batch.column(0).flatten().cast(pa.float64()).drop_null().to_numpy()
        top = max(top, float(np.abs(x[np.isfinite(x)]).max(initial=0.0)))
        n += batch.num_rows
    yield pa.RecordBatch.from_arrays([pa.array([top]), pa.array([n])], names=["top", "n"])


def units(rows: DataFrame, config: PQConfig, vector: str) -> tuple[float, float]:
    """(unit of coordinates, unit of squared errors): powers of two, UNIT where the data allow it.

    Sums of a batch must stay below 2**53 (floats) and sums of all rows below
    2**62 (whole numbers).
    """
    top, n = rows.select(vector).mapInArrow(_largest, "top double, n long").agg(F.max("top"), F.sum("n")).first()
    top, n = max(float(top or 0.0), 1e-150), max(1, n or 0)  # its square is no zero yet
    out = []
    for most in (top, 4 * top * top * config.dim):
        room = min(53 - np.log2(min(n, BATCH)), 62 - np.log2(n)) - np.log2(most)
        out.append(2.0 ** min(24, int(np.floor(room))))
    return out[0], out[1]


def sample(df: DataFrame, n: int, seed: int = 42, method: str = "hash", id_col: str = "vec_id", by: str | None = None) -> DataFrame:
    """About n rows (exactly, for hash), the same ones in every run."""
    if method == "hash":
        return df.orderBy(F.xxhash64(F.col(id_col), F.lit(seed)), id_col).limit(n)
    total = df.count()
    if method == "stratified":
        levels = [r[0] for r in df.select(by).distinct().collect()]
        return df.sampleBy(by, {v: min(1.0, n / max(1, total)) for v in levels}, seed)
    return df.filter(F.pmod(F.xxhash64(F.col(id_col), F.lit(seed)), F.lit(1_000_000)) < F.lit(int(1_000_000 * min(1.0, n / max(1, total)))))


def _rows(df: DataFrame, config: PQConfig, vector: str) -> np.ndarray:
    table = df.select(vector).toArrow()
    parts = [matrix(c, config.dim)[1] for c in table.column(0).chunks]
    return np.concatenate(parts).astype(np.float64) if parts else np.zeros((0, config.dim))


def seeds(df: DataFrame, config: PQConfig, id_col: str = "vec_id", vector: str = "embedding", pool: int = 16_384) -> PQModel:
    """first: rows with the k smallest ids; hash: k smallest hashes; weighted: by squared distance from a bounded pool; oversample: rounds of weighted draws, then weighted choice."""
    if config.init == "first":
        x = _rows(df.orderBy(id_col).limit(config.k), config, vector)
    elif config.init == "hash":
        x = _rows(sample(df, config.k, config.seed, id_col=id_col), config, vector)
    else:
        x = _rows(sample(df, pool, config.seed, id_col=id_col), config, vector)
    rng = np.random.Generator(np.random.PCG64(config.seed))
    shape = PQModel(config, [np.zeros((1, b - a)) for a, b in zip(config.offsets()[:-1], config.offsets()[1:], strict=True)])
    books = []
    for j in range(config.chunks):
        p = kernels.piece(x, shape, j)
        books.append(p if config.init in ("first", "hash") else _weighted(np.unique(p, axis=0), config.k, rng, 4 if config.init == "oversample" else 1))
    return PQModel(config, books)


def _weighted(p: np.ndarray, k: int, rng: np.random.Generator, batch: int) -> np.ndarray:
    """k rows drawn by squared distance to the nearest drawn so far; several at a time when oversampling, then thinned the same way."""
    if len(p) <= k:
        return p
    chosen = [int(rng.integers(len(p)))]
    near = ((p - p[chosen[0]]) ** 2).sum(axis=1)
    while len(set(chosen)) < k and near.sum() > 0:
        got = rng.choice(len(p), size=min(batch, len(p)), p=near / near.sum(), replace=batch > 1)
        for g in np.atleast_1d(got).tolist():
            chosen.append(g)
            near = np.minimum(near, ((p - p[g]) ** 2).sum(axis=1))
    return p[list(dict.fromkeys(chosen))[:k]]


def _partial_rows(sent, vector: str, kernel: tuple[str, dict], unit: tuple[float, float] = (float(UNIT), float(UNIT))):
    """(chunk, centroid, dim, total): whole-number sums of a partition; dim -1 counts rows, dim -2 adds up squared errors."""

    def rows(batches):
        model: PQModel = sent.value
        total: dict[int, np.ndarray] = {}
        for x in (x[a : a + BATCH] for batch in batches for x in (np.asarray(matrix(batch.column(0), model.config.dim)[1], np.float64),) for a in range(0, len(x), BATCH)):
            codes = kernels.encode(x, model, kernel[0], **kernel[1])
            for j in range(model.chunks):
                p, code, k = kernels.piece(x, model, j), codes[:, j].astype(np.int64), len(model.books[j])
                gap = p - model.books[j][code]
                columns = [np.floor(p[:, d] * unit[0] + 0.5) for d in range(p.shape[1])] + [np.ones(len(p)), np.floor((gap * gap).sum(axis=1) * unit[1] + 0.5)]
                part = np.stack([np.bincount(code, weights=c, minlength=k) for c in columns], axis=1).astype(np.int64)
                total[j] = total.get(j, 0) + part
        for j, part in total.items():
            k, width = part.shape
            dim = np.r_[np.arange(width - 2), -1, -2]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(k * width, j), pa.int32()), pa.array(np.repeat(np.arange(k), width), pa.int32()), pa.array(np.tile(dim, k), pa.int32()), pa.array(part.reshape(-1), pa.int64())], names=["chunk", "centroid", "dim", "total"])

    return rows


def lloyd(df: DataFrame, config: PQConfig, start: PQModel | None = None, id_col: str = "vec_id", vector: str = "embedding", score: str = "ranking", on_iteration=None, kernel: tuple[str, dict] | None = None) -> PQModel:
    """Train all chunks at once: tasks add up their rows by winner, the driver divides m * k sums.

    Every iteration starts from the same (sampled) rows, so the lineage stays
    flat.  Stops after config.iterations, when no sum changes, or when the
    relative gain in inertia falls below config.tol.  kernel names another
    encoding strategy and its options, for comparisons.
    """
    kernel = kernel or (("staged", {}) if score == "ranking" else ("tiled", {"score": score}))
    rows = sample(df, config.sample, config.seed, id_col=id_col) if config.sample else df
    kept = rows is df and df.storageLevel.useMemory  # by the caller; a second copy would push the first one to disk
    rows = rows.select(vector) if kept else rows.select(vector).persist()
    model = start or seeds(df, config, id_col, vector)
    inertia: list[float] = []
    spark = df.sparkSession
    unit = units(rows, config, vector)
    for _ in range(config.iterations):
        sent = spark.sparkContext.broadcast(model)
        partial = rows.mapInArrow(_partial_rows(sent, vector, kernel, unit), "chunk int, centroid int, dim int, total long")
        got = partial.groupBy("chunk", "centroid", "dim").agg(F.sum("total").alias("total")).toArrow()
        sent.destroy()
        model, error = _moved(model, got, config, unit)
        inertia.append(error)
        if on_iteration:
            on_iteration(model, error)
        if len(inertia) > 1 and (inertia[-2] == error or (config.tol and inertia[-2] - error < config.tol * inertia[-2])):
            break
    if not kept:
        rows.unpersist()
    return PQModel(config, model.books, inertia, model.model_id)


def _moved(model: PQModel, got: pa.Table, config: PQConfig, unit: tuple[float, float]) -> tuple[PQModel, float]:
    chunk, centroid, dim, total = (got.column(k).to_numpy() for k in range(4))
    books, error = [], 0
    for j, book in enumerate(model.books):
        here = chunk == j
        sums = np.zeros((len(book), book.shape[1] + 2), np.int64)
        sums[centroid[here], dim[here]] = total[here]  # -1 and -2 are the last two columns
        n = sums[:, -1]
        error += int(sums[:, -2].sum())
        new = book.copy()
        full = n > 0
        new[full] = sums[full, : book.shape[1]] / unit[0] / n[full, None]
        empty = np.flatnonzero(~full)
        if len(empty) and config.empty == "split":
            for e, big in zip(empty.tolist(), np.argsort(-n, kind="stable").tolist()):
                new[e] = new[big] * (1 + 1e-4)
        elif len(empty) and config.empty == "farthest":
            worst = np.argsort(-(sums[:, -2] / np.maximum(n, 1)), kind="stable")
            for e, w in zip(empty.tolist(), worst.tolist()):
                new[e] = new[w] + 1e-3
        books.append(new)
    return PQModel(config, books, model_id=model.model_id), error / unit[1]


def lloyd_sql(df: DataFrame, config: PQConfig, id_col: str = "vec_id", vector: str = "embedding") -> PQModel:
    """The same iterations in joins and aggregates; a baseline, and what the SQL oracle mirrors."""
    model = seeds(df, config, id_col, vector)
    subs = layout.split(df, config, "rows", id_col, vector)
    for _ in range(config.iterations):
        codes = enc.winners(enc.scored_rows(df, model, id_col=id_col, vector=vector), id_col=id_col)
        each = subs.join(codes.select(id_col, "chunk", "code"), [id_col, "chunk"]).select("chunk", "code", F.posexplode("sub").alias("dim", "x"))
        sums = each.groupBy("chunk", F.col("code").alias("centroid"), "dim").agg(F.sum(F.floor(F.col("x") * UNIT + 0.5)).alias("s"), F.count("*").alias("n"))
        books = [b.copy() for b in model.books]
        for r in sums.collect():
            books[r.chunk][r.centroid, r.dim] = r.s / float(UNIT) / r.n
        model = PQModel(config, books)
    return model


def lloyd_grouped(rows: DataFrame, config: PQConfig, id_col: str = "vec_id", vector: str = "embedding") -> PQModel:
    """One task per chunk on a bounded sample."""
    start = seeds(rows, config, id_col, vector)
    one = replace(config, dim=config.width, split="even")

    def fit(table: pa.Table) -> pa.Table:
        j = table.column("chunk")[0].as_py()
        x = np.array(table.column("sub").to_pylist())
        book = start.books[j]
        for _ in range(config.iterations):
            code = kernels.encode(x, PQModel(one, [book]))[:, 0].astype(np.int64)
            n = np.bincount(code, minlength=len(book))
            sums = np.stack([np.bincount(code, weights=np.floor(x[:, d] * UNIT + 0.5), minlength=len(book)) for d in range(x.shape[1])], axis=1)
            book = np.where(n[:, None] > 0, sums / UNIT / np.maximum(n, 1)[:, None], book)
        return pa.table({"chunk": pa.array([j] * len(book), pa.int32()), "centroid": pa.array(range(len(book)), pa.int32()), "coords": pa.array(book.tolist(), pa.list_(pa.float64()))})

    picked = sample(rows, config.sample or 65_536, config.seed, id_col=id_col)
    books = layout.split(picked, config, "rows", id_col, vector).select("chunk", "sub").groupBy("chunk").applyInArrow(fit, "chunk int, centroid int, coords array<double>")
    return PQModel.from_rows(config, books)


def refresh(model: PQModel, new: DataFrame, decay: float = 0.5, vector: str = "embedding") -> PQModel:
    """One pass over new rows: centroids move to the mean of their new rows, old places weighing decay."""
    sent = new.sparkSession.sparkContext.broadcast(model)
    unit = units(new, model.config, vector)
    partial = new.select(vector).mapInArrow(_partial_rows(sent, vector, ("staged", {}), unit), "chunk int, centroid int, dim int, total long")
    moved, error = _moved(model, partial.groupBy("chunk", "centroid", "dim").agg(F.sum("total").alias("total")).toArrow(), model.config, unit)
    return PQModel(model.config, [decay * a + (1 - decay) * b for a, b in zip(model.books, moved.books, strict=True)], [error], f"{model.model_id}+")


def effective_k(df: DataFrame, config: PQConfig, id_col: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(chunk, distinct, k_effective): fewer distinct pieces than k leave centroids unused."""
    subs = layout.split(df, config, "rows", id_col, vector)
    return subs.groupBy("chunk").agg(F.count_distinct("sub").alias("distinct")).withColumn("k_effective", F.least("distinct", F.lit(config.k).cast("long")))


def rotation(df: DataFrame, config: PQConfig, rounds: int = 3, pool: int = 4096, id_col: str = "vec_id", vector: str = "embedding") -> tuple[np.ndarray, PQModel]:
    """A rotation learned before the split, by turns with the codebooks (orthogonal Procrustes on a bounded sample)."""
    x = _rows(sample(df, pool, config.seed, id_col=id_col), config, vector)
    turn = np.eye(config.dim)
    rng = np.random.Generator(np.random.PCG64(config.seed))
    model = None
    for _ in range(rounds):
        y = x @ turn
        if model is None:
            base = PQModel(config, [np.zeros((1, b - a)) for a, b in zip(config.offsets()[:-1], config.offsets()[1:], strict=True)])
            model = PQModel(config, [_weighted(np.unique(kernels.piece(y, base, j), axis=0), config.k, rng, 1) for j in range(config.chunks)])
        for _ in range(2):
            codes = kernels.encode(y, model)
            books = []
            for j in range(config.chunks):
                p, c = kernels.piece(y, model, j), codes[:, j].astype(np.int64)
                n = np.bincount(c, minlength=len(model.books[j]))
                s = np.stack([np.bincount(c, weights=p[:, d], minlength=len(model.books[j])) for d in range(p.shape[1])], axis=1)
                books.append(np.where(n[:, None] > 0, s / np.maximum(n, 1)[:, None], model.books[j]))
            model = PQModel(config, books)
        codes = kernels.encode(y, model)
        back = np.concatenate([model.books[j][codes[:, j]] for j in range(config.chunks)], axis=1)[:, : config.dim]
        u, _, vt = np.linalg.svd(x.T @ back)
        turn = u @ vt
    return turn, model
