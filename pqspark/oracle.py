"""SQL that DuckDB runs on the same tables: the quantizer's definition, and what is derived from it."""

from __future__ import annotations


def rows(source: str = "embeddings", dim: int = 64, vector: str = "embedding") -> str:
    return f"e AS (SELECT vec_id, label, list_transform({vector}, lambda x: x::DOUBLE) AS v FROM {source})"


def cut(width: int, dim: int = 64) -> str:
    return f"sub AS (SELECT vec_id, label, j.range::INT AS chunk, v[j.range * {width} + 1 : j.range * {width} + {width}] AS x FROM e, range({dim // width}) j)"


def book(k: int, duplicate: int = 0) -> str:
    """First-k seeds; with duplicate, the first of them are listed twice."""
    if duplicate:
        return f"cb AS (SELECT chunk, (vec_id + d.range * {duplicate})::INT AS centroid, x AS c, list_dot_product(x, x) / 2 AS bias FROM sub, range(2) d WHERE vec_id < {duplicate})"
    return f"cb AS (SELECT chunk, vec_id::INT AS centroid, x AS c, list_dot_product(x, x) / 2 AS bias FROM sub WHERE vec_id < {k})"


def scored(score: str = "bias - list_dot_product(x, c)", cb: str = "cb") -> str:
    return f"sc AS (SELECT vec_id, label, s.chunk, centroid, x, c, {score} AS score FROM sub s JOIN {cb} b ON s.chunk = b.chunk)"


WON = "codes AS (SELECT * FROM sc QUALIFY row_number() OVER (PARTITION BY vec_id, chunk ORDER BY score, centroid) = 1)"


def base(width: int = 16, k: int = 16, duplicate: int = 0, score: str = "bias - list_dot_product(x, c)") -> str:
    return ", ".join((rows(), cut(width), book(k, duplicate), scored(score), WON))


def lloyd(iterations: int, width: int = 16, k: int = 16) -> str:
    """The codebook after so many iterations, as cb{iterations}; fixed-point sums, empty clusters keep their place."""
    parts = [rows(), cut(width), book(k).replace("cb AS", "cb0 AS")]
    for t in range(iterations):
        parts.append(f"w{t} AS MATERIALIZED (SELECT s.vec_id, s.chunk, s.x, b.centroid FROM sub s JOIN cb{t} b ON s.chunk = b.chunk QUALIFY row_number() OVER (PARTITION BY s.vec_id, s.chunk ORDER BY b.bias - list_dot_product(s.x, b.c), b.centroid) = 1)")
        parts.append(f"u{t} AS (SELECT chunk, centroid, d.range AS d, sum(floor(x[d.range + 1] * 16777216 + 0.5)::BIGINT)::DOUBLE / 16777216 / count(*) AS y FROM w{t}, range({width}) d GROUP BY 1, 2, 3)")
        parts.append(f"n{t} AS (SELECT chunk, centroid, list(y ORDER BY d) AS c FROM u{t} GROUP BY 1, 2)")
        parts.append(f"cb{t + 1} AS MATERIALIZED (SELECT b.chunk, b.centroid, coalesce(n.c, b.c) AS c, list_dot_product(coalesce(n.c, b.c), coalesce(n.c, b.c)) / 2 AS bias FROM cb{t} b LEFT JOIN n{t} n ON b.chunk = n.chunk AND b.centroid = n.centroid)")
    return ", ".join(parts)


CODES = "SELECT vec_id, string_agg(centroid::VARCHAR, ',' ORDER BY chunk) AS codes FROM codes GROUP BY vec_id"

EXACT = """pairs AS (SELECT q.vec_id AS query_id, b.vec_id, list_sum(list_transform(list_zip(q.v, b.v), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS dist FROM e q, e b WHERE q.vec_id % 20 = 0 AND q.vec_id <> b.vec_id),
truth AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id)::INT AS rank FROM pairs) WHERE rank <= 10)"""

LUT = "lut AS (SELECT s.vec_id AS query_id, s.chunk, centroid, list_sum(list_transform(list_zip(x, c), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS d FROM sub s JOIN cb ON s.chunk = cb.chunk WHERE s.vec_id % 20 = 0)"

ADC = LUT + """,
far AS (SELECT query_id, c.vec_id, any_value(c.label) AS label, sum(d) AS dist FROM codes c JOIN lut ON c.chunk = lut.chunk AND c.centroid = lut.centroid WHERE query_id <> c.vec_id GROUP BY 1, 2),
adc AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(dist, 9), vec_id)::INT AS rank FROM far)"""
