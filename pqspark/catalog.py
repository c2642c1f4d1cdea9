"""Every query of the engine by name, with its SQL oracle where SQL can express it.

Oracle queries take the first k rows as seeds (k = 16, pieces of 16 dimensions
unless a name says otherwise), so that SQL can state the codebook.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pqspark import oracle, relops, workloads
from pqspark.functions import sql as sql_functions
from pqspark.model import PQConfig, PQModel
from pqspark.operators import encode, index, layout, search, train, vectors
from pqspark.plans import cost
from pqspark.sources import tables
from pqspark.streaming import streams

Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_oracle: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        _queries[name] = f
        if sql:
            _oracle[name] = sql
        return f

    return add


def config(width: int = 16, k: int = 16, **more) -> PQConfig:
    return PQConfig(dim=64, width=width, k=k, init="first", **more)


def rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vectors.collection("emb64", spark, sf_dir)


def first_k(spark: SparkSession, sf_dir: str, width: int = 16, k: int = 16) -> PQModel:
    return train.seeds(rows(spark, sf_dir), config(width, k))


def queries_of(df: DataFrame) -> DataFrame:
    return df.filter("vec_id % 20 = 0")


def shown(codes: DataFrame, *keep: str) -> DataFrame:
    return codes.select("vec_id", *keep, layout.joined().alias("codes"))


def r6(c) -> F.Column:
    return F.round(c, 6)


# ------------------------------------------------------------------ layout

register("split_rows", f"WITH {oracle.rows()}, {oracle.cut(16)} SELECT vec_id, chunk, x AS sub FROM sub")(lambda s, d: layout.split(rows(s, d), config()))
register("split_cols", "SELECT vec_id, " + ", ".join(f"list_transform(embedding[{16 * j + 1}:{16 * j + 16}], lambda x: x::DOUBLE) AS s{j}" for j in range(4)) + " FROM embeddings")(lambda s, d: layout.split(rows(s, d), config(), "columns"))
register("bias", f"WITH {oracle.rows()}, {oracle.cut(16)}, {oracle.book(16)} SELECT chunk, centroid, round(bias, 9) AS bias FROM cb")(
    lambda s, d: layout.with_bias(layout.split(rows(s, d).filter("vec_id < 16"), config()).select("chunk", F.col("vec_id").cast("int").alias("centroid"), F.col("sub").alias("coords"))).select("chunk", "centroid", F.round("bias", 9).alias("bias"))
)
register("lanes", f"WITH {oracle.rows()}, {oracle.cut(16)}, {oracle.book(16)} SELECT chunk, d.range::INT AS dim, list(c[d.range + 1] ORDER BY centroid) AS lane FROM cb, range(16) d GROUP BY 1, 2")(lambda s, d: layout.to_lanes(first_k(s, d).codebook(s)))


@register("lanes_round_trip", f"WITH {oracle.rows()}, {oracle.cut(16)}, {oracle.book(16)} SELECT chunk, centroid, c AS coords FROM cb")
def _(s, d):
    return layout.from_lanes(layout.to_lanes(first_k(s, d).codebook(s)))


@register("pack_round_trip", f"WITH {oracle.base()} {oracle.CODES}")
def _(s, d):
    codes = encode.encode(rows(s, d), first_k(s, d))
    return shown(layout.unpack(layout.pack(codes, 4).drop("codes"), 4, 4))


# ---------------------------------------------------------------- encoding


def _encoded(name: str, width: int = 16, k: int = 16, sql: str | None = None, **options) -> None:
    register(name, sql or f"WITH {oracle.base(width, k)} {oracle.CODES}")(lambda s, d: shown(encode.encode(rows(s, d), first_k(s, d, width, k), **options)))


FULL = "list_sum(list_transform(list_zip(x, c), lambda z: (z[1] - z[2]) * (z[1] - z[2])))"
_encoded("encode_definition", strategy="relational", score="full", sql=f"WITH {oracle.base(score=FULL)} {oracle.CODES}")
_encoded("encode_matrix", strategy="relational", score="expanded", materialize=True)
_encoded("encode_matrix_kernel", strategy="matrix")
_encoded("encode_rowwise", strategy="rowwise")
_encoded("encode_expanded", strategy="expanded")
_encoded("encode_scalar_udf", strategy="scalar_udf")
_encoded("encode_full_tiled", strategy="tiled", score="full", order="row_major", tile=4, accumulate="fma")
_encoded("encode_tiled_chunk_order", strategy="tiled", score="full", order="block_chunk", tile=16)
_encoded("encode_row_major", strategy="tiled", order="row_major")
_encoded("encode_subspace_major", strategy="tiled", order="subspace_major", block_rows=64)
_encoded("encode_ranking", strategy="relational", score="ranking")
_encoded("encode_ranking2", strategy="relational", score="ranking2")
_encoded("encode_offset", strategy="relational", score="offset")
_encoded("encode_two_step", strategy="relational", winner="two_step")
_encoded("encode_staged")
_encoded("encode_staged_w8", width=8)
_encoded("encode_staged_tail", k=13, tile=8)
_encoded("encode_staged_f32", precision="f32")
_encoded("encode_hof", strategy="hof")
_encoded("encode_flat_expr", k=4, strategy="flat_expr")


@register("encode_ties", f"WITH {oracle.base(duplicate=8)} {oracle.CODES}")
def _(s, d):
    one = first_k(s, d, k=8)
    return shown(encode.encode(rows(s, d), PQModel(config(), [np.concatenate([b, b]) for b in one.books]), tile=4))


@register("decode", f"WITH {oracle.base()} SELECT vec_id, flatten(list(c ORDER BY chunk)) AS decoded FROM codes GROUP BY vec_id")
def _(s, d):
    model = first_k(s, d)
    return encode.decode(encode.encode(rows(s, d), model), model)


@register("distortion", f"WITH {oracle.base()} SELECT chunk, round(avg({FULL}), 6) AS mse, count(*) AS n FROM codes GROUP BY chunk")
def _(s, d):
    model = first_k(s, d)
    return encode.distortion(rows(s, d), encode.encode(rows(s, d), model), model).withColumn("mse", r6("mse"))


@register("score_to_distance", f"WITH {oracle.base()} SELECT vec_id, chunk, round({FULL}, 6) AS distance FROM codes")
def _(s, d):
    scored = encode.scored_rows(rows(s, d), first_k(s, d))
    won = encode.winners(scored).withColumnRenamed("code", "centroid").drop("score")
    return encode.score_to_distance(scored.join(won, ["vec_id", "chunk", "centroid"])).select("vec_id", "chunk", r6("distance").alias("distance"))


@register("agreement", "SELECT count(*) AS n_rows, count(*) AS equal, 0::BIGINT AS missing_a, 0::BIGINT AS missing_b FROM embeddings")
def _(s, d):
    model = first_k(s, d)
    return workloads.agreement(encode.encode(rows(s, d), model), encode.encode(rows(s, d), model, "expanded"))


_RESIDUAL = f"""WITH {oracle.rows()}, {oracle.cut(64)}, {oracle.book(4)}, {oracle.scored()}, {oracle.WON},
r AS (SELECT vec_id, centroid AS list, list_transform(list_zip(x, c), lambda z: z[1] - z[2]) AS v FROM codes),
s2 AS (SELECT vec_id, list, j.range::INT AS chunk, v[j.range * 16 + 1 : j.range * 16 + 16] AS x FROM r, range(4) j),
b2 AS (SELECT chunk, vec_id::INT AS centroid, x AS c, list_dot_product(x, x) / 2 AS bias FROM s2 WHERE vec_id < 16),
w2 AS (SELECT s2.vec_id, list, s2.chunk, centroid FROM s2 JOIN b2 ON s2.chunk = b2.chunk QUALIFY row_number() OVER (PARTITION BY s2.vec_id, s2.chunk ORDER BY bias - list_dot_product(x, c), centroid) = 1)
SELECT vec_id, list, string_agg(centroid::VARCHAR, ',' ORDER BY chunk) AS codes FROM w2 GROUP BY 1, 2"""


@register("encode_residual", _RESIDUAL)
def _(s, d):
    """Lists by whole vectors, codes of what is left over by a codebook of residuals (first rows as seeds in both)."""
    coarse = first_k(s, d, 64, 4)
    fine = train.seeds(encode.residuals(rows(s, d), coarse), config(), vector="residual")
    return encode.residual_encode(rows(s, d), coarse, fine).select("vec_id", "list", layout.joined().alias("codes"))


@register("encode_residual_trained")
def _(s, d):
    """Both stages trained; the fine one on residuals."""
    coarse, _ = index.coarse(rows(s, d), 4, init="first")
    left = encode.residuals(rows(s, d), coarse)
    fine = train.lloyd(left, PQConfig(k=16, iterations=5), vector="residual")
    return encode.residual_encode(rows(s, d), coarse, fine).select("vec_id", "list", layout.joined().alias("codes"))


@register("encode_rotated")
def _(s, d):
    turn, model = train.rotation(rows(s, d), PQConfig(dim=64, width=16, k=16))
    book = F.array(*(F.array(*(F.lit(float(x)) for x in turn[:, j])) for j in range(64)))
    turned = rows(s, d).select("vec_id", F.transform(book, lambda c: layout.dot(layout.doubles(), c)).alias("embedding"))
    return shown(encode.encode(turned, model))


@register("incremental_new_rows", "SELECT vec_id FROM embeddings WHERE vec_id >= 100")
def _(s, d):
    have = rows(s, d).filter("vec_id < 100").select("vec_id", F.xxhash64("embedding").alias("content"))
    return encode.only_new(rows(s, d), have).select("vec_id")


# ---------------------------------------------------------------- training


def _lloyd_sql(t: int) -> str:
    return f"WITH {oracle.lloyd(t)} SELECT chunk, centroid, list_transform(c, lambda x: round(x, 9)) AS coords FROM cb{t}"


def _book(s: SparkSession, model: PQModel) -> DataFrame:
    return model.codebook(s).select("chunk", "centroid", F.transform("coords", lambda x: F.round(x, 9)).alias("coords"))


register("lloyd_1", _lloyd_sql(1))(lambda s, d: _book(s, train.lloyd(rows(s, d), config(iterations=1))))
register("lloyd_3", _lloyd_sql(3))(lambda s, d: _book(s, train.lloyd(rows(s, d), config(iterations=3))))
register("lloyd_3_full_score", _lloyd_sql(3))(lambda s, d: _book(s, train.lloyd(rows(s, d), config(iterations=3), score="full")))
register("lloyd_sql_3", _lloyd_sql(3))(lambda s, d: _book(s, train.lloyd_sql(rows(s, d), config(iterations=3))))
register("train_grouped", _lloyd_sql(3))(lambda s, d: _book(s, train.lloyd_grouped(rows(s, d), config(iterations=3, sample=1_000_000))))
register("train_sampled")(lambda s, d: _book(s, train.lloyd(rows(s, d), PQConfig(k=16, sample=256, iterations=5))))
register("train_weighted_seeds")(lambda s, d: _book(s, train.lloyd(rows(s, d), PQConfig(k=16, init="weighted", iterations=5))))
register("train_oversampled_seeds")(lambda s, d: _book(s, train.lloyd(rows(s, d), PQConfig(k=16, init="oversample", iterations=5))))
register("train_refresh", f"WITH {oracle.lloyd(1)} SELECT b.chunk, b.centroid, list_transform(list_zip(b.c, n.c), lambda z: round(0.5 * z[1] + 0.5 * z[2], 9)) AS coords FROM cb0 b JOIN cb1 n ON b.chunk = n.chunk AND b.centroid = n.centroid")(lambda s, d: _book(s, train.refresh(first_k(s, d), rows(s, d))))
register("effective_k", f"WITH {oracle.rows()}, {oracle.cut(16)} SELECT chunk, count(DISTINCT x) AS \"distinct\", least(count(DISTINCT x), 16) AS k_effective FROM sub GROUP BY chunk")(lambda s, d: train.effective_k(rows(s, d), config()))

# ------------------------------------------------------------------ search

_found = lambda df: df.withColumn("dist", r6("dist"))
register("exact_knn", f"WITH {oracle.rows()}, {oracle.EXACT} SELECT query_id, rank, vec_id, round(dist, 6) AS dist FROM truth")(lambda s, d: _found(search.exact(queries_of(rows(s, d)), rows(s, d))))
register("exact_knn_sql", f"WITH {oracle.rows()}, {oracle.EXACT} SELECT query_id, rank, vec_id, round(dist, 6) AS dist FROM truth")(lambda s, d: _found(search.exact_sql(queries_of(rows(s, d)), rows(s, d))))


@register("lut", f"WITH {oracle.base()}, {oracle.LUT} SELECT query_id, chunk, list(round(d, 9) ORDER BY centroid) AS lut FROM lut GROUP BY 1, 2")
def _(s, d):
    return search.lut(queries_of(rows(s, d)), first_k(s, d)).withColumn("lut", F.transform("lut", lambda x: F.round(x, 9)))


def found_by_codes(s: SparkSession, d: str, k: int, **options) -> tuple[DataFrame, DataFrame]:
    """(the k candidates of each query by asymmetric distance, all vectors); equal codes have equal sums, so ties are those of the SQL's rounded ones."""
    e, model = rows(s, d), first_k(s, d)
    return search.adc(queries_of(e), encode.encode(e, model, keep=("label",)), model, k, **options), e


register("adc_topk", f"WITH {oracle.base()}, {oracle.ADC} SELECT query_id, rank, vec_id, round(dist, 6) AS dist FROM adc WHERE rank <= 10")(lambda s, d: _found(found_by_codes(s, d, 10)[0]))
register("filtered_adc", f"WITH {oracle.base()}, {oracle.LUT}, far AS (SELECT query_id, c.vec_id, sum(d) AS dist FROM codes c JOIN lut ON c.chunk = lut.chunk AND c.centroid = lut.centroid WHERE query_id <> c.vec_id AND label < 3 GROUP BY 1, 2) SELECT query_id, vec_id, round(dist, 6) AS dist, row_number() OVER (PARTITION BY query_id ORDER BY round(dist, 9), vec_id)::INT AS rank FROM far QUALIFY rank <= 10")(
    lambda s, d: _found(found_by_codes(s, d, 10, where=F.col("label") < 3)[0])
)


@register(
    "sdc_topk",
    f"WITH {oracle.base()}, p AS (SELECT q.vec_id AS query_id, b.vec_id, round(sum(list_sum(list_transform(list_zip(q.c, b.c), lambda z: (z[1] - z[2]) * (z[1] - z[2])))), 9) AS dist FROM codes q JOIN codes b ON q.chunk = b.chunk AND q.vec_id <> b.vec_id WHERE q.vec_id % 20 = 0 GROUP BY 1, 2) SELECT query_id, vec_id, round(dist, 6) AS dist, row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id)::INT AS rank FROM p QUALIFY rank <= 10",
)
def _(s, d):
    model = first_k(s, d)
    codes = encode.encode(rows(s, d), model)
    return _found(search.sdc(queries_of(codes), codes, model))


register("rerank_topk", f"WITH {oracle.base()}, {oracle.ADC}, p AS (SELECT a.query_id, a.vec_id, list_sum(list_transform(list_zip(q.v, b.v), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS dist FROM adc a JOIN e q ON q.vec_id = a.query_id JOIN e b ON b.vec_id = a.vec_id WHERE rank <= 50) SELECT query_id, vec_id, round(dist, 6) AS dist, row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id)::INT AS rank FROM p QUALIFY rank <= 10")(
    lambda s, d: (lambda c, e: _found(search.rerank(c, queries_of(e), e)))(*found_by_codes(s, d, 50))
)
_HITS = f"WITH {oracle.base()}, {oracle.ADC}, {oracle.EXACT}"


def _truth(s, d):
    return search.exact(queries_of(rows(s, d)), rows(s, d))


register("recall_at_10", f"{_HITS} SELECT t.query_id, count(a.vec_id) / count(*) AS recall FROM truth t LEFT JOIN (SELECT * FROM adc WHERE rank <= 10) a ON a.query_id = t.query_id AND a.vec_id = t.vec_id GROUP BY 1")(lambda s, d: search.recall(found_by_codes(s, d, 10)[0], _truth(s, d), 10))
register("recall_curve", f"{_HITS}, h AS (SELECT a.rank AS l, count(*) AS n FROM adc a JOIN truth t ON a.query_id = t.query_id AND a.vec_id = t.vec_id WHERE a.rank <= 100 GROUP BY 1) SELECT l, round(sum(n) OVER (ORDER BY l) / (SELECT count(*) FROM truth), 9) AS recall FROM h")(
    lambda s, d: search.recall_curve(found_by_codes(s, d, 100)[0], _truth(s, d), 10).withColumn("recall", F.round("recall", 9))
)
register("tune_candidates", f"{_HITS}, h AS (SELECT a.rank AS l, count(*) AS n FROM adc a JOIN truth t ON a.query_id = t.query_id AND a.vec_id = t.vec_id GROUP BY 1), c AS (SELECT l, sum(n) OVER (ORDER BY l) / (SELECT count(*) FROM truth) AS recall FROM h) SELECT min(l)::INT AS l FROM c WHERE recall >= 0.95")(
    lambda s, d: (lambda e, model: s.createDataFrame([(search.needed(queries_of(e), encode.encode(e, model), model, _truth(s, d), 10, 0.95),)], "l int"))(rows(s, d), first_k(s, d))
)
register("false_positives", f"{_HITS} SELECT a.query_id, round(1 - count(t.vec_id) / count(*), 9) AS rate FROM adc a LEFT JOIN truth t ON a.query_id = t.query_id AND a.vec_id = t.vec_id WHERE a.rank <= 20 GROUP BY 1")(
    lambda s, d: search.false_positives(found_by_codes(s, d, 20)[0], _truth(s, d), 20).withColumn("rate", F.round("rate", 9))
)

# ----------------------------------------------------------------- measures

def shapes(s: SparkSession, d: str) -> list[tuple[int, int]]:
    """(dimensions, rows) of the vectors of embeddings, as read."""
    return [tuple(r) for r in rows(s, d).filter("embedding IS NOT NULL").groupBy(F.size("embedding").alias("dim")).agg(F.count("*").alias("n")).orderBy("dim").collect()]


_SHAPES = "d AS (SELECT len(embedding)::BIGINT AS dim, count(*) AS n FROM embeddings WHERE embedding IS NOT NULL GROUP BY 1), w AS (SELECT unnest([2, 4, 8, 16, 32]) AS w)"
register("sizes", f"WITH {_SHAPES}, c AS (SELECT w, dim, n, ((dim + w - 1) // w)::INT AS m FROM d, w) SELECT w::INT AS width, dim::INT AS dim, m * 8 AS bits, m AS bytes, 32.0::DOUBLE * dim / (m * 8) AS ratio, (n * m)::BIGINT AS table_bytes FROM c")(
    lambda s, d: s.createDataFrame([(w, dim, *(of := cost.sizes(dim, -(-dim // w), 8)), n * of[1]) for dim, n in shapes(s, d) for w in (2, 4, 8, 16, 32)], "width int, dim int, bits int, bytes int, ratio double, table_bytes long")
)


def _counted(s: SparkSession, d: str) -> tuple[int, int]:
    """(rows, dimensions) of embeddings, both from its rows."""
    n, dim = rows(s, d).agg(F.count("*"), F.max(F.size("embedding"))).first()
    return n, dim if dim and dim > 0 else 64


register(
    "cost_model",
    "WITH n AS (SELECT count(*) AS n FROM embeddings) SELECT s AS strategy, k AS counter, v::BIGINT AS value FROM (SELECT unnest([{'s': 'expanded', 'k': 'arithmetic', 'v': n * 124 + 3 * n * 4 * 256 + n * 256 * 124}, {'s': 'staged', 'k': 'arithmetic', 'v': n * 256 * 124 + n * 4 * 256}, {'s': 'expanded', 'k': 'score_cells', 'v': n * 1024}, {'s': 'staged', 'k': 'score_cells', 'v': 0}, {'s': 'expanded', 'k': 'distances', 'v': n * 1024}, {'s': 'staged', 'k': 'distances', 'v': n * 1024}], recursive := true) FROM n)",
)(lambda s, d: cost.model(s, *_counted(s, d), 4, 256, ("expanded", "staged")).filter("counter IN ('arithmetic', 'score_cells', 'distances')"))
_COST = """WITH p AS (SELECT count(*) AS n, 64 AS d, 4 AS m, 256 AS k FROM embeddings),
s AS (SELECT unnest(['lane_by_dimension', 'matrix', 'expanded', 'tiled_full', 'staged']) AS s),
v AS (SELECT s, n, d, m, k, n * k * (2 * d - m) AS ranked, n * (2 * d - m) AS norms, ceil(n / 2048.0)::BIGINT * m AS blocks FROM p, s),
c AS (SELECT s, unnest([
    {'k': 'arithmetic', 'v': CASE s WHEN 'lane_by_dimension' THEN n * k * (3 * d - m) WHEN 'tiled_full' THEN n * k * (3 * d - m) WHEN 'staged' THEN ranked + n * m * k ELSE norms + 3 * n * m * k + ranked END},
    {'k': 'compares', 'v': n * m * (k - 1)}, {'k': 'distances', 'v': n * m * k},
    {'k': 'score_cells', 'v': CASE WHEN s IN ('tiled_full', 'staged') THEN 0 ELSE n * m * k END},
    {'k': 'live_score_bytes', 'v': CASE s WHEN 'lane_by_dimension' THEN 4 * k WHEN 'matrix' THEN 4 * n * k WHEN 'expanded' THEN 4 * 2048 * k ELSE 4 * 2048 * 16 END},
    {'k': 'codebook_switches', 'v': CASE s WHEN 'matrix' THEN m WHEN 'tiled_full' THEN blocks WHEN 'staged' THEN blocks ELSE n * m END},
    {'k': 'bytes_in', 'v': 4 * n * d}, {'k': 'bytes_out', 'v': n * m}, {'k': 'codebook_bytes', 'v': 4 * k * (d + m)}, {'k': 'offline', 'v': 2 * k * d}, {'k': 'transfer_bytes', 'v': n * (4 * d + m)}], recursive := true) FROM v)
SELECT s AS strategy, k AS counter, v::BIGINT AS value FROM c"""
register("cost_model_all", _COST)(lambda s, d: cost.model(s, *_counted(s, d), 4, 256))
register("lane_utilisation", f"WITH {_SHAPES}, k AS (SELECT least(256, sum(n)) AS k FROM d), u AS (SELECT w, sum(n * dim)::DOUBLE AS used, sum(n * 16 * ((dim // w) * ceil(w / 16.0) + ceil((dim % w) / 16.0)))::DOUBLE AS lanes FROM d, w GROUP BY w) SELECT w::INT AS width, used / lanes AS by_dimension, (k / (16 * ceil(k / 16.0)))::DOUBLE AS by_centroid FROM u, k")(
    lambda s, d: (lambda of: s.createDataFrame([(w, *cost.lanes_used(of, w, 16, 256)) for w in (2, 4, 8, 16, 32) if of], "width int, by_dimension double, by_centroid double"))(shapes(s, d))
)
register("working_set", f"WITH {_SHAPES}, t AS (SELECT max(dim) AS dim, least(256, sum(n)) AS k FROM d) SELECT w::INT AS width, (4 * k * least(w, dim) + 4 * k)::INT AS bytes FROM t, w WHERE k > 0")(
    lambda s, d: (lambda of: s.createDataFrame([(w, cost.working_set(min(w, of[-1][0]), min(256, sum(n for _, n in of)))) for w in (2, 4, 8, 16, 32) if of], "width int, bytes int"))(shapes(s, d))
)


@register("code_entropy", f"WITH {oracle.base()}, h AS (SELECT chunk, centroid, count(*) AS n FROM codes GROUP BY 1, 2), t AS (SELECT count(*)::DOUBLE AS t FROM embeddings) SELECT chunk, count(*) AS used, round(-sum(n / t * log2(n / t)), 6) AS entropy, round(max(n / t), 6) AS max_share FROM h, t GROUP BY chunk")
def _(s, d):
    return workloads.usage(encode.encode(rows(s, d), first_k(s, d)))


# ------------------------------------------------------------ index, graphs

register("knn_graph", f"WITH {oracle.rows()}, p AS (SELECT a.vec_id AS src, b.vec_id AS dst, list_sum(list_transform(list_zip(a.v, b.v), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS dist FROM e a, e b WHERE a.vec_id <> b.vec_id) SELECT src, dst, round(dist, 6) AS dist, row_number() OVER (PARTITION BY src ORDER BY dist, dst)::INT AS rank FROM p QUALIFY rank <= 5")(
    lambda s, d: _found(index.knn_graph(rows(s, d), 5))
)
register("coarse_assign", f"WITH {oracle.rows()}, {oracle.cut(64)}, {oracle.book(8)}, {oracle.scored()}, {oracle.WON} SELECT vec_id, centroid AS list FROM codes")(
    lambda s, d: encode.encode(rows(s, d), first_k(s, d, 64, 8)).select("vec_id", F.get("codes", F.lit(0)).cast("int").alias("list"))
)
register("graph_build")(lambda s, d: index.build_graph(rows(s, d), 16, 32, block_rows=400))


@register("beam_search")
def _(s, d):
    e, model = rows(s, d), train.lloyd(rows(s, d), config(width=4, iterations=5))
    codes, graph = encode.encode(e, model), index.build_graph(e, 16, 32)
    return index.beam(queries_of(e), graph, codes, model, e, [0, 1, 2, 3], width=64)


@register("insert_delete", f"WITH {oracle.base()} SELECT * FROM ({oracle.CODES}) WHERE vec_id % 7 <> 0")
def _(s, d):
    e, model = rows(s, d), first_k(s, d)
    half = encode.encode(e.filter("vec_id < 300"), model).withColumn("model_id", F.lit("pq"))
    return shown(index.delete(index.insert(half, e.filter("vec_id >= 250"), model), e.filter("vec_id % 7 = 0").select("vec_id")))


# -------------------------------------------------------------- collections


@register("emb_ladder_128", "WITH n AS (SELECT count(*) AS n FROM embeddings) SELECT a.vec_id, list_transform(list_concat(a.embedding, b.embedding), lambda x: x::DOUBLE) AS embedding FROM embeddings a, n, embeddings b WHERE b.vec_id = (a.vec_id + 7) % n")
def _(s, d):
    return vectors.ladder(s, d, 128).select("vec_id", layout.doubles().alias("embedding"))


def _hash_sql(source: str, id_: str, dim: int) -> str:
    return f"WITH x AS ({source}), t AS (SELECT {id_}, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS t FROM x) SELECT {id_}, (('0x' || substr(md5(t), 1, 4))::INT % {dim})::INT AS bucket, count(*) AS n FROM t WHERE t <> '' GROUP BY 1, 2"


register("doc_hash", _hash_sql("SELECT doc_id, text FROM documents", "doc_id", 256))(lambda s, d: vectors.hashed(vectors.table(s, d, "documents").select("doc_id", "text"), "doc_id", 256))
register("page_hash", _hash_sql("SELECT page_id, regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g') AS text FROM pages", "page_id", 256))(lambda s, d: vectors.hashed(vectors.page_texts(s, d), "page_id", 256))
register("conv_hash", _hash_sql("SELECT conv_id, string_agg(text, ' ' ORDER BY turn, text) AS text FROM conversations GROUP BY 1", "conv_id", 128))(lambda s, d: vectors.hashed(vectors.conversation_texts(s, d), "conv_id", 128))


@register("line_feat_hist", "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity / 50), 4) AS q, round(sum(month(l_shipdate) / 12.0), 4) AS m, round(sum(dayofweek(l_shipdate) / 7.0), 4) AS w FROM lineitem GROUP BY 1")
def _(s, d):
    at = lambda k: F.round(F.sum(F.get("embedding", F.lit(k))), 4)
    return vectors.line_features(s, d).groupBy("l_returnflag").agg(F.count("*").alias("n"), at(0).alias("q"), at(4).alias("m"), at(5).alias("w"))


@register("user_hours", "SELECT user_id AS vec_id, list_transform(list_value(" + ", ".join(f"count(*) FILTER (hour(ts) = {h}) / count(*)" for h in range(24)) + ", avg(value), min(value), max(value)), lambda x: round(x, 6)) AS embedding FROM events GROUP BY 1")
def _(s, d):
    wide = vectors.user_hours(s, d)
    return wide.select("vec_id", F.transform(F.concat(F.slice("embedding", 1, 24), F.slice("embedding", F.size("embedding") - 2, F.lit(3))), lambda x: F.round(x, 6)).alias("embedding"))


@register("cust_profile", "WITH l AS (SELECT l_orderkey, sum(l_quantity) AS q, sum(l_discount) AS d, count(*) AS n FROM lineitem GROUP BY 1) SELECT o_custkey AS vec_id, list_transform([" + ", ".join(f"count(*) FILTER (month(o_orderdate) = {m})::DOUBLE" for m in range(1, 13)) + ", avg(o_totalprice), CASE WHEN sum(n) > 0 THEN sum(q) / sum(n) ELSE 0 END, CASE WHEN sum(n) > 0 THEN sum(d) / sum(n) ELSE 0 END, coalesce(sum(n), 0)::DOUBLE], lambda x: round(x, 6)) AS embedding FROM orders LEFT JOIN l ON l_orderkey = o_orderkey GROUP BY 1")
def _(s, d):
    return vectors.customer_profile(s, d).withColumn("embedding", F.transform("embedding", lambda x: vectors.rounded(x, 6)))


# ------------------------------------------------------------------ streams


def work_folder(s: SparkSession) -> str:
    """A new folder in the shared one; a temporary one only in one local process that names none, as in tests."""
    shared = s.conf.get("spark.checkpoint.dir", None)
    if not shared:
        if not s.sparkContext.master.startswith("local") or s.sparkContext.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
        shared = tempfile.mkdtemp(prefix="pqspark-")
    return f"{shared.rstrip('/')}/stream-{uuid.uuid4().hex}"


def vector_stream(s: SparkSession, d: str, path: str, files: int = 4) -> DataFrame:
    rows(s, d).select("vec_id", "embedding", "label").repartition(files).write.parquet(f"{path}/in")
    return streams.read(s, f"{path}/in")


def event_stream(s: SparkSession, d: str, path: str) -> DataFrame:
    """events in four batches, their time as a zoned timestamp."""
    e = vectors.table(s, d, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), "value")
    e.repartition(4).write.parquet(f"{path}/in")
    return streams.read(s, f"{path}/in", e.schema.simpleString()[7:-1].replace(":", " "))


@register("stream_encode", f"WITH {oracle.base()} {oracle.CODES}")
def _(s, d):
    """embeddings read as a stream, encoded by the batch plan, into a table of its own."""
    path = work_folder(s)
    made = streams.encoded(vector_stream(s, d, path), first_k(s, d))
    query = made.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/log").trigger(availableNow=True).start()
    query.awaitTermination()
    return shown(s.read.parquet(f"{path}/out"))


@register("stream_drift", f"WITH {oracle.base()}, g AS (SELECT vec_id, sum(list_sum(list_transform(list_zip(x, c), lambda z: (z[1] - z[2]) * (z[1] - z[2])))) AS sse FROM codes GROUP BY 1) SELECT (vec_id // 24) * 86400 AS start, count(*) AS n, round(avg(sse), 6) AS mean_sse FROM g GROUP BY 1")
def _(s, d):
    """Mean squared error of codes in daily windows; a row arrives each hour, and batches come in any order: the watermark waits for the whole span of the table."""
    path, (first, last) = work_folder(s), rows(s, d).agg(F.min("vec_id"), F.max("vec_id")).first()
    late = max(3650, ((last or 0) - (first or 0)) // 24 + 2)
    timed = vector_stream(s, d, path).withColumn("ts", F.timestamp_seconds(F.col("vec_id") * 3600)).withColumn("embedding_copy", F.col("embedding"))
    made = streams.drift(streams.errors(timed, first_k(s, d), keep=("ts",)), late=f"{late} days")
    return streams.settled(made, path, ["start"]).select(F.unix_seconds("start").alias("start"), "n", r6("mean_sse").alias("mean_sse"))


@register("stream_sessions", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 6 HOUR THEN 0 ELSE 1 END AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), i AS (SELECT user_id, ts, sum(first) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM g) SELECT user_id, epoch_us(max(ts)) - epoch_us(min(ts)) AS lasted, count(*) AS n FROM i GROUP BY user_id, s")
def _(s, d):
    """Sessions of users' events with gaps of six hours: how long from first to last event, and events."""
    path = work_folder(s)
    made = streams.sessions(event_stream(s, d, path), gap="6 hours", late="3650 days")
    lasted = F.unix_micros("end") - F.unix_micros("start") - 6 * 3_600_000_000
    return streams.settled(made, path, ["user_id", "start"], "complete").select("user_id", lasted.alias("lasted"), "n")


@register("stream_dedupe", "SELECT vec_id, label FROM embeddings")
def _(s, d):
    """Every tenth id is sent twice, an hour apart; one of each is kept."""
    path = work_folder(s)
    at = rows(s, d).select("vec_id", "label", F.timestamp_seconds(F.col("vec_id")).alias("ts"))
    sent = at.unionByName(at.filter("vec_id % 10 = 0").withColumn("ts", F.col("ts") + F.expr("INTERVAL 1 HOUR")))
    sent.repartition(4).write.parquet(f"{path}/in")
    kept = streams.dedupe(streams.read(s, f"{path}/in", "vec_id long, label int, ts timestamp"), horizon="3650 days")
    return streams.settled(kept, path, [], "append").select("vec_id", "label")


@register("stream_counts", f"WITH {oracle.base()} SELECT chunk, centroid AS code, count(*) AS n FROM codes GROUP BY 1, 2")
def _(s, d):
    """Uses of each code, counted on over batches."""
    path = work_folder(s)
    made = streams.running_counts(streams.encoded(vector_stream(s, d, path), first_k(s, d)))
    return streams.settled(made, path, ["chunk", "code"])


@register("stream_join", f"WITH {oracle.base()}, made AS ({oracle.CODES}) SELECT event_id, codes FROM events JOIN made ON user_id = vec_id")
def _(s, d):
    """Events as a stream with the code of the vector of their user's number."""
    path = work_folder(s)
    codes = shown(encode.encode(rows(s, d), first_k(s, d))).withColumnRenamed("vec_id", "user_id")
    made = streams.with_static(event_stream(s, d, path), codes, "user_id").select("event_id", "codes")
    return streams.settled(made, path, [], "append")


@register("w11_insertion", f"WITH {oracle.base()}, made AS ({oracle.CODES}) SELECT vec_id, codes FROM made WHERE vec_id % 7 <> 0")
def _(s, d):
    """Vectors inserted in ten batches, every seventh deleted by an eleventh: the codes table equals a batch encoding of what is left."""
    path = work_folder(s)
    change = lambda df, op, ts: df.select("vec_id", "embedding", F.timestamp_seconds(F.lit(ts)).alias("ts"), F.lit(0).alias("seq"), F.lit(op).alias("op"))
    change(rows(s, d), "upsert", 1).repartition(10).write.parquet(f"{path}/in")
    change(rows(s, d).filter("vec_id % 7 = 0"), "delete", 2).coalesce(1).write.mode("append").parquet(f"{path}/in")
    changes = streams.read(s, f"{path}/in", "vec_id long, embedding array<float>, ts timestamp, seq int, op string")
    query = streams.upsert(changes, first_k(s, d), f"{path}/codes", f"{path}/log")
    query.awaitTermination()
    last = s.read.parquet(f"{path}/codes").agg(F.max("v")).first()[0]
    return shown(s.read.parquet(f"{path}/codes/v={last}"))


@register("stream_stream_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_type = 'purchase' AND a.event_id <> b.event_id AND a.ts BETWEEN b.ts - INTERVAL 1 HOUR AND b.ts + INTERVAL 1 HOUR")
def _(s, d):
    """Events and purchases, both as streams: what else a user did within an hour of a purchase."""
    path = work_folder(s)
    e = vectors.table(s, d, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), "event_type")
    e.repartition(2).write.parquet(f"{path}/in")
    read = lambda: streams.read(s, f"{path}/in", "event_id long, user_id long, ts timestamp, event_type string")
    bought = read().filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("ts_right"))
    made = streams.near_in_time(read().select("user_id", F.col("event_id").alias("a"), "ts"), bought, "user_id", late="3650 days").filter("a <> b").select("a", "b")
    return streams.settled(made, path, [], "append")


# ------------------------------------------------------------------- tables


@register("table_formats", f"WITH {oracle.base()}, made AS ({oracle.CODES}) SELECT kind, vec_id, codes FROM made, (VALUES ('json'), ('orc'), ('parquet')) f(kind)")
def _(s, d):
    """The codes written in three formats, each table replaced once by itself, and read with a declared schema."""
    path, codes, out = work_folder(s), encode.encode(rows(s, d), first_k(s, d)).select("vec_id", F.col("codes").cast("array<bigint>").alias("codes")), []
    for kind in ("json", "orc", "parquet"):
        tables.write(codes, f"{path}/{kind}", kind)
        tables.write(tables.read(s, f"{path}/{kind}", "vec_id long, codes array<bigint>", kind), f"{path}/{kind}", kind)
        out.append(shown(tables.read(s, f"{path}/{kind}", "vec_id long, codes array<bigint>", kind)).withColumn("kind", F.lit(kind)))
    return out[0].unionByName(out[1]).unionByName(out[2])


@register("scan_partitioned", f"WITH {oracle.rows()}, {oracle.cut(64)}, {oracle.book(8)}, {oracle.scored()}, {oracle.WON} SELECT vec_id, centroid AS list FROM codes WHERE centroid IN (1, 3)")
def _(s, d):
    """Rows in folders by coarse list; a scan of two lists opens two folders."""
    path = f"{work_folder(s)}/lists"
    made = encode.encode(rows(s, d), first_k(s, d, 64, 8)).select("vec_id", F.get("codes", F.lit(0)).cast("int").alias("list"))
    tables.write_lists(made, path)
    return tables.scan_lists(s, path, [1, 3])


@register("coarse_probes", f"WITH {oracle.rows()}, {oracle.cut(64)}, {oracle.book(8)}, {oracle.scored()} SELECT vec_id AS query_id, centroid AS list FROM sc WHERE vec_id % 20 = 0 QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY score, centroid) <= 2")
def _(s, d):
    return index.probes(queries_of(rows(s, d)), first_k(s, d, 64, 8), 2)


@register("sort_codes", f"WITH {oracle.base()} {oracle.CODES}")
def _(s, d):
    return shown(tables.sort_codes(encode.encode(rows(s, d), first_k(s, d))))


@register("udtf_chunks", f"WITH {oracle.base()} SELECT vec_id, chunk, centroid AS code FROM codes")
def _(s, d):
    """Codes by the table function, one row a chunk."""
    sql_functions.register(s, first_k(s, d))
    return s.sql("SELECT vec_id, chunk, code FROM {e}, LATERAL pq_chunks(embedding)", e=rows(s, d))


# ------------------------------------------------------ the rest by their own


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Train, encode, and find each query's ten nearest by lookup tables."""
    e = rows(spark, sf_dir)
    model = train.lloyd(e, config(iterations=3))
    return search.adc(queries_of(e), encode.encode(e, model), model, 10)


register("flagship")(flagship)


def queries() -> dict[str, Query]:
    return _queries | relops.queries() | workloads.queries()


def oracle_sql() -> dict[str, str]:
    return _oracle | relops.oracle_sql()

