"""Relational work around codes: joins, aggregates, windows and functions over encoded vectors."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pqspark import oracle
from pqspark.model import PQConfig
from pqspark.operators import encode, layout, search, train, vectors

_queries: dict = {}
_oracle: dict[str, str] = {}
BASE = f"WITH {oracle.base()}"


def register(name: str, sql: str):
    def add(f):
        _queries[name], _oracle[name] = f, sql
        return f

    return add


def table(s: SparkSession, d: str, name: str) -> DataFrame:
    return vectors.table(s, d, name)


def codes(s: SparkSession, d: str) -> DataFrame:
    """(vec_id, label, codes) of embeddings by the first sixteen rows."""
    e = table(s, d, "embeddings")
    return encode.encode(e, train.seeds(e, PQConfig(k=16, init="first")), keep=("label",))


def each(s: SparkSession, d: str) -> DataFrame:
    return codes(s, d).select("vec_id", "label", F.posexplode("codes").alias("chunk", "code")).withColumn("code", F.col("code").cast("int"))


register("scan_pruned", "SELECT vec_id, label FROM embeddings WHERE vec_id < 100")(lambda s, d: table(s, d, "embeddings").filter("vec_id < 100").select("vec_id", "label"))
register("scan_from_text", "SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS embedding FROM embeddings")(
    lambda s, d: vectors.from_text(table(s, d, "embeddings").select("vec_id", F.to_json("embedding").alias("t")), "t").select("vec_id", layout.doubles().alias("embedding"))
)
register("codes_wide", f"{BASE} SELECT vec_id, " + ", ".join(f"max(centroid) FILTER (chunk = {j})::SMALLINT AS c{j}" for j in range(4)) + " FROM codes GROUP BY 1")(lambda s, d: codes(s, d).select("vec_id", *(F.get("codes", F.lit(j)).alias(f"c{j}") for j in range(4))))
register("codes_hex", f"{BASE} SELECT vec_id, string_agg(printf('%02X', centroid), '' ORDER BY chunk) AS code FROM codes GROUP BY 1")(lambda s, d: codes(s, d).select("vec_id", F.hex(layout.pack_sql()).alias("code")))
register("codes_filter", f"{BASE} SELECT vec_id FROM codes WHERE chunk = 0 AND centroid = 3 AND label < 5")(lambda s, d: codes(s, d).filter("label < 5 AND codes[0] = 3").select("vec_id"))


@register("rejects", "SELECT * FROM (VALUES (-1::BIGINT, 'null vector'), (-2, 'wrong length'), (-3, 'null component'), (-4, 'not finite')) t(vec_id, reason)")
def _(s, d):
    bad = s.sql("SELECT -1L AS vec_id, CAST(NULL AS array<float>) AS embedding UNION ALL SELECT -2L, array(CAST(1 AS float)) UNION ALL SELECT -3L, array_repeat(CAST(NULL AS float), 64) UNION ALL SELECT -4L, array_repeat(CAST('NaN' AS float), 64)")
    return vectors.validate(table(s, d, "embeddings").select("vec_id", "embedding").unionByName(bad), 64)[1].select("vec_id", "reason")


register("join_codes_docs", f"{BASE} SELECT vec_id, chunk, centroid AS code, lang, n_chars FROM codes JOIN documents ON doc_id = vec_id")(
    lambda s, d: each(s, d).join(table(s, d, "documents").select(F.col("doc_id").alias("vec_id"), "lang", "n_chars"), "vec_id").select("vec_id", "chunk", "code", "lang", "n_chars")
)


@register("join_broadcast", f"WITH {oracle.rows()}, {oracle.cut(16)}, {oracle.book(16)} SELECT vec_id, s.chunk, centroid, round(list_dot_product(x, c), 6) AS product FROM sub s JOIN cb USING (chunk)")
def _(s, d):
    e = table(s, d, "embeddings")
    book = train.seeds(e, PQConfig(k=16, init="first")).codebook(s)
    subs = layout.split(e, PQConfig(k=16))
    return subs.join(F.broadcast(book), "chunk").select("vec_id", "chunk", "centroid", F.round(layout.dot("sub", "coords"), 6).alias("product"))


@register("join_theta", "SELECT a.vec_id AS a, b.vec_id AS b FROM embeddings a, embeddings b WHERE a.vec_id < b.vec_id AND list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: (z[1]::DOUBLE - z[2]) * (z[1]::DOUBLE - z[2]))) < 1.6")
def _(s, d):
    """All pairs under a distance: queries in blocks against all rows, within the tasks."""
    return search.within(table(s, d, "embeddings"), table(s, d, "embeddings"), 1.6).filter("query_id < vec_id").select(F.col("query_id").alias("a"), F.col("vec_id").alias("b"))


@register("join_range", "SELECT c_custkey, (floor(c_acctbal / 1000))::BIGINT AS band FROM customer WHERE c_acctbal >= 0 AND c_acctbal < 10000")
def _(s, d):
    bands = s.range(10).select(F.col("id").alias("band"), (F.col("id") * 1000).alias("lo"), ((F.col("id") + 1) * 1000).alias("hi"))
    c = table(s, d, "customer").withColumn("bucket", F.floor(F.col("c_acctbal") / 1000))
    return c.join(F.broadcast(bands), (F.col("bucket") == F.col("band")) & (F.col("c_acctbal") >= F.col("lo")) & (F.col("c_acctbal") < F.col("hi"))).select("c_custkey", "band")


@register("join_asof", "SELECT event_id, CASE WHEN ts >= TIMESTAMP '2024-01-20' THEN 'c' WHEN ts >= TIMESTAMP '2024-01-10' THEN 'b' WHEN ts >= TIMESTAMP '2024-01-01' THEN 'a' END AS version FROM events")
def _(s, d):
    versions = s.sql("SELECT * FROM VALUES (TIMESTAMP '2024-01-01', 'a'), (TIMESTAMP '2024-01-10', 'b'), (TIMESTAMP '2024-01-20', 'c') AS t(ts, version)")
    # the versions' spans are few: a lookup by range, no window over all events
    spans = versions.withColumn("until", F.lead("ts").over(Window.orderBy("ts"))).withColumnRenamed("ts", "since")
    on = (F.col("ts") >= F.col("since")) & (F.col("until").isNull() | (F.col("ts") < F.col("until")))
    return table(s, d, "events").join(F.broadcast(spans), on, "left").select("event_id", "version")


@register("join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_type = 'purchase' AND a.event_id <> b.event_id AND a.ts BETWEEN b.ts - INTERVAL 1 HOUR AND b.ts + INTERVAL 1 HOUR")
def _(s, d):
    e = table(s, d, "events")
    a, b = e.select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta")), e.filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"))
    return a.join(b, "user_id").filter("a <> b AND ta BETWEEN tb - INTERVAL 1 HOUR AND tb + INTERVAL 1 HOUR").select("a", "b")


register("join_semi", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")(lambda s, d: table(s, d, "documents").select("doc_id").join(table(s, d, "labels"), "doc_id", "left_semi"))
register("join_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")(lambda s, d: table(s, d, "documents").select("doc_id").join(table(s, d, "labels"), "doc_id", "left_anti"))
register("join_full", "SELECT vec_id, a.label AS a, b.label AS b FROM (SELECT * FROM embeddings WHERE vec_id < 300) a FULL JOIN (SELECT * FROM embeddings WHERE vec_id >= 200) b USING (vec_id)")(
    lambda s, d: table(s, d, "embeddings").filter("vec_id < 300").select("vec_id", F.col("label").alias("a")).join(table(s, d, "embeddings").filter("vec_id >= 200").select("vec_id", F.col("label").alias("b")), "vec_id", "full")
)


@register("lateral_top", f"{BASE} SELECT vec_id, chunk, centroid, row_number() OVER (PARTITION BY vec_id, chunk ORDER BY round(score, 9), centroid)::INT AS rank FROM sc QUALIFY rank <= 3")
def _(s, d):
    e = table(s, d, "embeddings")
    scored = encode.scored_rows(e, train.seeds(e, PQConfig(k=16, init="first"))).withColumn("score", F.round("score", 9))
    rank = F.row_number().over(Window.partitionBy("vec_id", "chunk").orderBy("score", "centroid"))
    return scored.withColumn("rank", rank).filter("rank <= 3").select("vec_id", "chunk", "centroid", "rank")


register("agg_code_hist", f"{BASE} SELECT chunk, centroid AS code, count(*) AS n FROM codes GROUP BY 1, 2")(lambda s, d: each(s, d).groupBy("chunk", "code").agg(F.count("*").alias("n")))
register("agg_distinct", f"{BASE} SELECT chunk, count(DISTINCT centroid) AS n FROM codes GROUP BY 1")(lambda s, d: each(s, d).groupBy("chunk").agg(F.count_distinct("code").alias("n")))
register("agg_cube", f"{BASE} SELECT label, chunk, count(*) AS n, sum(centroid) AS s FROM codes GROUP BY CUBE (label, chunk)")(lambda s, d: each(s, d).cube("label", "chunk").agg(F.count("*").alias("n"), F.sum("code").alias("s")))
register("agg_rollup", "SELECT lang, source, count(*) AS n, sum(n_chars) AS c FROM documents GROUP BY ROLLUP (lang, source)")(lambda s, d: table(s, d, "documents").rollup("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("c")))


@register("agg_gsets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def _(s, d):
    return table(s, d, "documents").groupingSets([[F.col("lang")], [F.col("source")], []], "lang", "source").agg(F.count("*").alias("n"))


@register("agg_vector_mean", "SELECT label, list(round(m, 6) ORDER BY d) AS mean FROM (SELECT label, d.range AS d, avg(embedding[d.range + 1]::DOUBLE) AS m FROM embeddings, range(64) d GROUP BY 1, 2) GROUP BY 1")
def _(s, d):
    dims = table(s, d, "embeddings").groupBy("label").agg(*(F.avg(F.get("embedding", F.lit(k)).cast("double")).alias(f"m{k}") for k in range(64)))
    return dims.select("label", F.array(*(F.round(f"m{k}", 6) for k in range(64))).alias("mean"))


@register("agg_stats", "SELECT round(var_samp(embedding[1]::DOUBLE), 6) AS v, round(corr(embedding[1]::DOUBLE, embedding[2]::DOUBLE), 6) AS c, round(quantile_cont(embedding[1]::DOUBLE, 0.5), 6) AS p FROM embeddings")
def _(s, d):
    x = lambda k: F.get("embedding", F.lit(k)).cast("double")
    return table(s, d, "embeddings").agg(F.round(F.var_samp(x(0)), 6).alias("v"), F.round(F.corr(x(0), x(1)), 6).alias("c"), F.round(F.percentile(x(0), 0.5), 6).alias("p"))


register("agg_pivot", f"{BASE} SELECT chunk, " + ", ".join(f"count(*) FILTER (centroid % 4 = {j}) AS b{j}" for j in range(4)) + " FROM codes GROUP BY 1")(
    lambda s, d: each(s, d).withColumn("b", F.concat(F.lit("b"), F.col("code") % 4)).groupBy("chunk").pivot("b", [f"b{j}" for j in range(4)]).count().na.fill(0)
)
def _window():
    return Window.partitionBy("label").orderBy("vec_id")


register("win_rank", "SELECT vec_id, (row_number() OVER w)::INT AS r, (dense_rank() OVER w)::INT AS dr, (ntile(4) OVER w)::INT AS q FROM embeddings WINDOW w AS (PARTITION BY label ORDER BY vec_id)")(
    lambda s, d: table(s, d, "embeddings").select("vec_id", F.row_number().over(_window()).alias("r"), F.dense_rank().over(_window()).alias("dr"), F.ntile(4).over(_window()).alias("q"))
)
register("win_lead", "SELECT vec_id, lead(vec_id) OVER w - vec_id AS gap, lag(vec_id) OVER w AS before FROM embeddings WINDOW w AS (PARTITION BY label ORDER BY vec_id)")(
    lambda s, d: table(s, d, "embeddings").select("vec_id", (F.lead("vec_id").over(_window()) - F.col("vec_id")).alias("gap"), F.lag("vec_id").over(_window()).alias("before"))
)


@register("win_frames", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 6) AS moving, round(sum(value) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW), 4) AS hour FROM events")
def _(s, d):
    by = Window.partitionBy("user_id")
    rows_, span = by.orderBy("ts", "event_id").rowsBetween(-3, 0), by.orderBy(F.round(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000).cast("long")).rangeBetween(-3600, 0)
    return table(s, d, "events").select("event_id", F.round(F.avg("value").over(rows_), 6).alias("moving"), F.round(F.sum("value").over(span), 4).alias("hour"))


register("topk", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20")(lambda s, d: table(s, d, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(20))
register("set_ops", "(SELECT vec_id FROM embeddings WHERE vec_id < 300 INTERSECT SELECT vec_id FROM embeddings WHERE vec_id >= 100) EXCEPT SELECT vec_id FROM embeddings WHERE label = 3 UNION ALL SELECT vec_id FROM embeddings WHERE vec_id < 5")(
    lambda s, d: (lambda e: e.filter("vec_id < 300").select("vec_id").intersect(e.filter("vec_id >= 100").select("vec_id")).exceptAll(e.filter("label = 3").select("vec_id").distinct()).unionByName(e.filter("vec_id < 5").select("vec_id")))(table(s, d, "embeddings"))
)


@register("fn_math", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x))), 6) AS norm, round(list_sum(list_transform(embedding, lambda x: abs(x::DOUBLE))), 6) AS l1 FROM embeddings")
def _(s, d):
    v = layout.doubles()
    return table(s, d, "embeddings").select("vec_id", F.round(F.sqrt(layout.dot(v, v)), 6).alias("norm"), F.round(F.aggregate(F.transform(v, F.abs), F.lit(0.0), lambda a, x: a + x), 6).alias("l1"))


register("fn_array", "SELECT vec_id, list_position(embedding, list_min(embedding))::BIGINT - 1 AS argmin, len(list_filter(embedding, lambda x: x > 0))::INT AS positive FROM embeddings")(
    lambda s, d: table(s, d, "embeddings").select("vec_id", (F.array_position("embedding", F.array_min("embedding")) - 1).alias("argmin"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"))
)


@register("fn_map", f"{BASE}, h AS (SELECT chunk, centroid, count(*) AS n FROM codes GROUP BY 1, 2) SELECT chunk, string_agg(centroid || ':' || n, ',' ORDER BY centroid) AS counts FROM h GROUP BY 1")
def _(s, d):
    m = each(s, d).groupBy("chunk", "code").agg(F.count("*").alias("n")).groupBy("chunk").agg(F.map_from_entries(F.collect_list(F.struct("code", "n"))).alias("m"))
    return m.select("chunk", F.array_join(F.transform(F.array_sort(F.map_entries("m")), lambda e: F.concat_ws(":", e.key, e.value)), ",").alias("counts"))


register("fn_json", "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")(lambda s, d: table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k")))


@register("passthrough", "SELECT l_returnflag, sum(l_extendedprice::DECIMAL(12,2))::DECIMAL(22,2) AS price, count(*) AS n FROM lineitem GROUP BY 1")
def _(s, d):
    lines = vectors.line_features(s, d).withColumn("price", F.col("l_extendedprice").cast("decimal(12,2)"))
    model = train.seeds(lines.limit(64), PQConfig(dim=8, width=4, k=8, init="hash"))
    made = encode.encode(lines, model, keep=("l_returnflag", "price"))
    return made.groupBy("l_returnflag").agg(F.sum("price").cast("decimal(22,2)").alias("price"), F.count("codes").alias("n"))


@register("encode_udf_sql", f"{BASE} {oracle.CODES}")
def _(s, d):
    from pqspark.functions import sql

    e = table(s, d, "embeddings")
    sql.register(s, train.seeds(e, PQConfig(k=16, init="first")))
    e.createOrReplaceTempView("pq_rows")
    return s.sql("SELECT vec_id, array_join(cast(pq_encode(embedding) AS array<string>), ',') AS codes FROM pq_rows")


def queries() -> dict:
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    return dict(_oracle)
