"""Code generation: strategies that all give the same codes, decoding and distortion."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from pqspark.functions import kernels
from pqspark.functions.arrow import matrix
from pqspark.functions.arrow import vectors as as_lists
from pqspark.model import PQModel
from pqspark.operators import layout, vectors

KERNELS = ("staged", "tiled", "expanded", "matrix", "lane_by_dimension", "rowwise")
DECLARED = ("relational", "hof", "flat_expr", "scalar_udf")


def encode(
    df: DataFrame,
    model: PQModel,
    strategy: str = "staged",
    id_col: str = "vec_id",
    vector: str = "embedding",
    keep: tuple[str, ...] = (),
    out: str = "array",
    on_bad: str = "reject",
    **options,
) -> DataFrame:
    """df's id, kept columns and codes (array<smallint>, array<int> beyond 32 768 centroids), code (binary), or both.

    One narrow pass: columns are chosen below the map, so that the scan reads
    only these; the model is broadcast, rows stream through.  Rows with a null
    vector, a wrong length, or null or non-finite components are left out
    (reject), get null codes (null_code), or raise (fail), whatever the strategy.
    """
    if on_bad not in ("reject", "null_code", "fail") or out not in ("array", "binary", "both"):
        raise ValueError("on_bad is reject, null_code or fail; out is array, binary or both")
    if strategy in DECLARED:
        return _declared(df, model, strategy, id_col, vector, keep, out, on_bad, **options)
    if strategy not in KERNELS:
        raise ValueError(f"strategy must be one of {(*KERNELS, *DECLARED)}")
    source = df.select(id_col, *keep, vector)
    fields = [f for f in source.schema.fields if f.name != vector]
    fields += [T.StructField("codes", T.ArrayType(T.ShortType() if model.code_type == "smallint" else T.IntegerType()))] if out in ("array", "both") else []
    fields += [T.StructField("code", T.BinaryType())] if out in ("binary", "both") else []
    sent = df.sparkSession.sparkContext.broadcast(model)
    dim, bits = model.config.dim, model.config.bits

    def rows(batches):
        own = sent.value
        for batch in batches:
            at = batch.schema.get_field_index(vector)
            whole, x = matrix(batch.column(at), dim)
            if len(whole) < batch.num_rows:
                if on_bad == "fail":
                    raise ValueError(f"{batch.num_rows - len(whole)} vectors can't be encoded")
                if on_bad == "reject":
                    batch = batch.take(pa.array(whole))
            codes = kernels.encode(np.asarray(x, np.float64), own, strategy, **options)
            columns = [c for k, c in enumerate(batch.columns) if k != at]
            if on_bad == "null_code" and len(whole) < batch.num_rows:
                place = np.full(batch.num_rows, -1)
                place[whole] = np.arange(len(whole))
                take = pa.array([None if p < 0 else p for p in place.tolist()], pa.int64())
            else:
                take = None
            made = []
            if out in ("array", "both"):
                made.append(pa.ListArray.from_arrays(pa.array(np.arange(0, codes.size + 1, codes.shape[1]), pa.int32()), pa.array(codes.reshape(-1))))
            if out in ("binary", "both"):
                made.append(pa.array(kernels.pack(codes, bits), pa.binary()))
            columns += [c if take is None else c.take(take) for c in made]
            yield pa.RecordBatch.from_arrays(columns, names=[f.name for f in fields])

    return source.mapInArrow(rows, T.StructType(fields))


def _declared(df: DataFrame, model: PQModel, strategy: str, id_col: str, vector: str, keep: tuple[str, ...], out: str, on_bad: str, **options) -> DataFrame:
    """The strategies that are expressions or joins, with bad vectors set aside before them."""
    why = vectors.reason(vector, model.config.dim)
    if on_bad == "fail":
        good = df.withColumn(vector, F.when(why.isNull(), F.col(vector)).otherwise(F.raise_error(F.concat(F.lit("a vector can't be encoded: "), why))))
    else:
        good = df.filter(why.isNull())
    run = {"relational": relational, "hof": hof, "flat_expr": flat, "scalar_udf": scalar_udf}[strategy]
    made = run(good, model, id_col, vector, keep, **options)
    made = made.withColumn("codes", F.col("codes").cast(f"array<{model.code_type}>"))
    if out != "array":
        made = layout.pack(made, model.config.bits)
    made = made if out != "binary" else made.drop("codes")
    if on_bad != "null_code":
        return made
    missing = [F.lit(None).cast(f.dataType).alias(f.name) for f in made.schema.fields if f.name in ("codes", "code")]
    return made.unionByName(df.filter(why.isNotNull()).select(id_col, *keep, *missing))


def profiled(df: DataFrame, model: PQModel, strategy: str = "staged", vector: str = "embedding", **options) -> DataFrame:
    """(n, cpu_s, faults, switches, peak_mb) of each batch: what the system counts while a kernel encodes it."""
    sent = df.sparkSession.sparkContext.broadcast(model)

    def rows(batches):
        import resource

        own = sent.value
        for batch in batches:
            _, x = matrix(batch.column(0), own.config.dim)
            x = np.asarray(x, np.float64)
            a = resource.getrusage(resource.RUSAGE_SELF)
            kernels.encode(x, own, strategy, **options)
            b = resource.getrusage(resource.RUSAGE_SELF)
            told = (len(x), b.ru_utime + b.ru_stime - a.ru_utime - a.ru_stime, b.ru_minflt + b.ru_majflt - a.ru_minflt - a.ru_majflt, b.ru_nvcsw + b.ru_nivcsw - a.ru_nvcsw - a.ru_nivcsw, b.ru_maxrss / 1024)
            yield pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(told, (pa.int64(), pa.float64(), pa.int64(), pa.int64(), pa.float64()), strict=True)], names=["n", "cpu_s", "faults", "switches", "peak_mb"])

    return df.select(vector).mapInArrow(rows, "n long, cpu_s double, faults long, switches long, peak_mb double")


def scored_rows(df: DataFrame, model: PQModel, score: str = "ranking", alpha: Column | None = None, id_col: str = "vec_id", vector: str = "embedding", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, chunk, centroid, score) of every piece and centroid: the table that the matrix baseline materializes."""
    subs = layout.split(df, model.config, "rows", id_col, vector, keep)
    pairs = subs.join(F.broadcast(model.codebook(df.sparkSession)), "chunk")
    ranking = F.col("bias") - layout.dot("sub", "coords")
    value = {
        "full": layout.squared("sub", "coords"),
        "expanded": layout.dot("sub", "sub") + 2 * F.col("bias") - 2 * layout.dot("sub", "coords"),
        "ranking": ranking,
        "ranking2": 2 * F.col("bias") - 2 * layout.dot("sub", "coords"),
        "offset": layout.squared("sub", "coords") - (alpha if alpha is not None else layout.dot("sub", "sub")),
    }[score]
    return pairs.select(id_col, *keep, "chunk", "centroid", value.alias("score"), "sub")


def winners(scored: DataFrame, winner: str = "struct", id_col: str = "vec_id", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, chunk, code): the smallest score, the smallest centroid among equals."""
    by = [id_col, *keep, "chunk"]
    if winner == "struct":
        return scored.groupBy(*by).agg(F.min(F.struct("score", "centroid")).alias("w")).select(*by, F.col("w.centroid").alias("code"), F.col("w.score").alias("score"))
    least = scored.groupBy(*by).agg(F.min("score").alias("least"))
    ties = scored.join(least, by).filter(F.col("score") == F.col("least"))
    return ties.groupBy(*by).agg(F.min("centroid").alias("code"), F.min("score").alias("score"))


def collected(won: DataFrame, id_col: str = "vec_id", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, codes) in chunk order from (id, chunk, code)."""
    codes = F.transform(F.array_sort(F.collect_list(F.struct("chunk", "code"))), lambda s: s.code.cast("int"))
    return won.groupBy(id_col, *keep).agg(codes.alias("codes"))


def relational(df: DataFrame, model: PQModel, id_col: str = "vec_id", vector: str = "embedding", keep: tuple[str, ...] = (), score: str = "ranking", winner: str = "struct", materialize: bool = False, alpha: Column | None = None) -> DataFrame:
    """The definition in joins and aggregates; materialize keeps the whole score table first (the matrix baseline)."""
    scored = scored_rows(df, model, score, alpha, id_col, vector, keep)
    if materialize:
        scored = scored.drop("sub").persist()
    return collected(winners(scored, winner, id_col, keep), id_col, keep)


def _array(values) -> Column:
    return F.array(*(F.lit(float(v)) for v in values))


def _ranking_of(sub: Column):
    return lambda s: s.b - layout.dot(sub, s.c)


def hof(df: DataFrame, model: PQModel, id_col: str = "vec_id", vector: str = "embedding", keep: tuple[str, ...] = ()) -> DataFrame:
    """Without Python or joins: higher-order functions over literal codebooks; for small k."""
    found = []
    for j, sub in enumerate(layout.pieces(model.config, vector)):
        book = F.array(*(F.struct(_array(c).alias("c"), F.lit(float(b)).alias("b")) for c, b in zip(model.books[j], model.bias[j], strict=True)))
        value = F.transform(book, _ranking_of(sub))
        found.append((F.array_position(value, F.array_min(value)) - 1).cast("smallint"))
    return df.select(id_col, *keep, F.array(*found).alias("codes"))


def flat(df: DataFrame, model: PQModel, id_col: str = "vec_id", vector: str = "embedding", keep: tuple[str, ...] = ()) -> DataFrame:
    """One generated expression per chunk; refused beyond k * dimensions = 256, where a method would outgrow the JVM's limit."""
    if model.k * model.config.dim > 256:
        raise ValueError("k * dimensions must be 256 at most for flat expressions")
    v, found = layout.doubles(vector), []
    for j, book in enumerate(model.books):
        ranked = []
        for c, centroid in enumerate(book):
            product = F.lit(0.0)
            for d, x in enumerate(centroid):
                product = product + F.get(v, F.lit(model.offsets[j] + d)) * F.lit(float(x))
            ranked.append(F.struct((F.lit(float(model.bias[j][c])) - product).alias("s"), F.lit(c).alias("c")))
        found.append((F.least(*ranked) if len(ranked) > 1 else ranked[0]).getField("c").cast("smallint"))
    return df.select(id_col, *keep, F.array(*found).alias("codes"))


def scalar_udf(df: DataFrame, model: PQModel, id_col: str = "vec_id", vector: str = "embedding", keep: tuple[str, ...] = ()) -> DataFrame:
    """One pickled row at a time across the process border: the analogue of an offload with a transfer per vector."""

    @F.udf("array<smallint>", useArrow=False)
    def one(v):
        return kernels.encode(np.array([v]), model)[0].tolist()

    return df.select(id_col, *keep, one(vector).alias("codes"))


def _centroids(codes: pa.Array, model: PQModel) -> np.ndarray:
    """[rows, dimensions]: the centroids of the codes in a row."""
    code = codes.flatten().to_numpy().reshape(len(codes), model.chunks)
    return np.concatenate([book[code[:, j]] for j, book in enumerate(model.books)], axis=1)[:, : model.config.dim]


def decode(codes: DataFrame, model: PQModel, id_col: str = "vec_id", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, decoded): the centroids of the codes in a row, in one narrow pass; rows without codes are left out."""
    source = codes.filter(F.col("codes").isNotNull()).select(id_col, *keep, "codes")
    sent = codes.sparkSession.sparkContext.broadcast(model)

    def rows(batches):
        for batch in batches:
            decoded = _centroids(batch.column(batch.num_columns - 1), sent.value) if batch.num_rows else np.zeros((0, sent.value.config.dim))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], as_lists(decoded, pa.float64())], names=[*batch.schema.names[:-1], "decoded"])

    return source.mapInArrow(rows, T.StructType([*source.schema.fields[:-1], T.StructField("decoded", T.ArrayType(T.DoubleType()))]))


def distortion(df: DataFrame, codes: DataFrame, model: PQModel, by: tuple[str, ...] = (), id_col: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(by..., chunk, mse, n): mean squared error of the codes, by chunk; one join by id, and sums of a task's rows before the shuffle."""
    pairs = df.select(id_col, *by, vector).join(codes.filter(F.col("codes").isNotNull()).select(id_col, "codes"), id_col).select(*by, vector, "codes")
    sent = df.sparkSession.sparkContext.broadcast(model)
    m = model.chunks

    def rows(batches):
        own = sent.value
        for batch in batches:
            good, x = matrix(batch.column(batch.num_columns - 2), own.config.dim)
            if len(good) < batch.num_rows:
                batch = batch.take(pa.array(good))
            if not batch.num_rows:
                continue
            gap = np.asarray(x, np.float64) - _centroids(batch.column(batch.num_columns - 1), own)
            cut = [o for o in own.offsets[:-1] if o < own.config.dim]
            error = np.add.reduceat(gap * gap, cut, axis=1)
            kept = [c.take(pa.array(np.repeat(np.arange(batch.num_rows), m))) for c in batch.columns[:-2]]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(np.tile(np.arange(m, dtype=np.int32), batch.num_rows)), pa.array(error.reshape(-1))], names=[*by, "chunk", "error"])

    fields = [*pairs.schema.fields[:-2], T.StructField("chunk", T.IntegerType()), T.StructField("error", T.DoubleType())]
    return pairs.mapInArrow(rows, T.StructType(fields)).groupBy(*by, "chunk").agg(F.avg("error").alias("mse"), F.count("*").alias("n"))


def score_to_distance(scored: DataFrame) -> DataFrame:
    """Squared distance from the ranking score: the piece's squared norm and twice the score."""
    return scored.withColumn("distance", layout.dot("sub", "sub") + 2 * F.col("score"))


def only_new(df: DataFrame, encoded: DataFrame, id_col: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """Rows that encoded(id, content) does not hold yet, or holds with another content hash."""
    keyed = df.withColumn("content", F.xxhash64(vector))
    return keyed.join(encoded.select(id_col, "content"), [id_col, "content"], "left_anti")


def residuals(df: DataFrame, coarse: PQModel, id_col: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(id, list, residual): the list of the coarse model (one chunk) and what its centroid leaves over, in one narrow pass."""
    sent = df.sparkSession.sparkContext.broadcast(coarse)

    def rows(batches):
        own = sent.value
        for batch in batches:
            good, x = matrix(batch.column(1), own.config.dim)
            x = np.asarray(x, np.float64)
            found = kernels.encode(x, own)[:, 0].astype(np.int32) if len(x) else np.zeros(0, np.int32)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(good, pa.int64())), pa.array(found), as_lists(x - own.books[0][found], pa.float64())], names=[id_col, "list", "residual"])

    return df.select(F.col(id_col), vector).mapInArrow(rows, f"{id_col} long, list int, residual array<double>")


def residual_encode(df: DataFrame, coarse: PQModel, fine: PQModel, id_col: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(id, list, codes): two stages in narrow passes; fine is a model of residuals (train it on residuals())."""
    return encode(residuals(df, coarse, id_col, vector), fine, id_col=id_col, vector="residual", keep=("list",))
