"""Vector collections on the given tables, validation and scaling."""

from __future__ import annotations

import re
from collections import Counter
from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pqspark.functions.arrow import vectors as lists
from pqspark.operators import layout

#: A token of hashed texts, and how many of them a task remembers the buckets of.
TOKEN, KNOWN = re.compile(rb"[a-z]+"), 1 << 18


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def reason(vector: str, dim: int) -> Column:
    """Why a vector can't be encoded; null for good ones."""
    v = F.col(vector)
    return (
        F.when(v.isNull(), "null vector")
        .when(F.size(v) != dim, "wrong length")
        .when(F.exists(v, lambda x: x.isNull()), "null component")
        .when(F.exists(v, lambda x: F.isnan(x) | (F.abs(x) == float("inf"))), "not finite")
    )


def validate(df: DataFrame, dim: int, vector: str = "embedding") -> tuple[DataFrame, DataFrame]:
    """(good rows, rejected rows with a reason)."""
    told = df.withColumn("reason", reason(vector, dim))
    return told.filter("reason IS NULL").drop("reason"), told.filter("reason IS NOT NULL")


def normalize(df: DataFrame, vector: str = "embedding") -> DataFrame:
    norm = F.sqrt(layout.dot(layout.doubles(vector), layout.doubles(vector)))
    return df.withColumn("_n", norm).withColumn(vector, F.when(F.col("_n") > 0, F.transform(layout.doubles(vector), lambda x: x / F.col("_n"))).otherwise(layout.doubles(vector))).drop("_n")


def scale(df: DataFrame, factor: float, vector: str = "embedding") -> DataFrame:
    return df.withColumn(vector, F.transform(layout.doubles(vector), lambda x: x * factor))


def from_text(df: DataFrame, column: str) -> DataFrame:
    """A JSON or bracketed, comma-separated text column to a vector column."""
    return df.withColumn("embedding", F.from_json(column, "array<float>"))


def in_order(df: DataFrame, key: str, ranges: int = 64) -> DataFrame:
    """df with _at, a row's place from 0 in order of a number; rows are numbered range by range, those of equal number by their content."""
    bounds = sorted(set(df.approxQuantile(key, [k / ranges for k in range(1, ranges)], 0.001)))
    at = F.size(F.filter(F.array(*map(F.lit, bounds)), lambda b: b <= F.col(key))) if bounds else F.lit(0)
    ranged = df.withColumn("_range", at)
    before, n = [], 0
    for r in ranged.groupBy("_range").count().orderBy("_range").collect():
        before.append((r[0], n))
        n += r[1]
    starts = F.broadcast(df.sparkSession.createDataFrame(before, "_range int, _start long"))
    row = F.row_number().over(Window.partitionBy("_range").orderBy(key, *(c for c in df.columns if c != key)))
    return ranged.withColumn("_row", row).join(starts, "_range").withColumn("_at", F.col("_start") + F.col("_row") - 1).drop("_range", "_start", "_row")


def ladder(spark: SparkSession, sf_dir: str, dim: int, step: int = 7, whole: bool = False) -> DataFrame:
    """embeddings cut to dim, or extended by the vectors of ids step, 2 * step, ... further on (modulo the row count).

    That is for ids 0, 1, ...; a row with another id may find no partner and is left out, as by the SQL.  whole: rows are
    told apart by their places in order of id, which are the same for ids 0, 1, ..., and all stay.
    """
    e = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    if dim <= 64:
        return e.select("vec_id", F.slice("embedding", 1, dim).alias("embedding"))
    n = e.count()
    blocks = -(-dim // 64)
    out = e = in_order(e, "vec_id") if whole else e.withColumn("_at", F.col("vec_id"))
    for r in range(1, blocks):
        shifted = e.select(F.pmod(F.col("_at") - r * step, F.lit(n)).alias("_at"), F.col("embedding").alias(f"_{r}"))
        out = out.join(shifted, "_at")
    return out.select("vec_id", F.slice(F.concat("embedding", *(f"_{r}" for r in range(1, blocks))), 1, dim).alias("embedding"))


def hashed(texts: DataFrame, id_col: str, dim: int) -> DataFrame:
    """(id, bucket, n) token counts of texts(id, text): letters only, bucket from the first hex digits of the token's MD5."""
    tokens = texts.select(id_col, F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("t")).filter("t <> ''")
    bucket = F.pmod(F.conv(F.substring(F.md5("t"), 1, 4), 16, 10).cast("int"), F.lit(dim))
    return tokens.groupBy(id_col, bucket.alias("bucket")).agg(F.count("*").alias("n"))


def _bucket_of(tokens: list[bytes], dim: int) -> np.ndarray:
    return np.array([int(md5(t).hexdigest()[:4], 16) % dim for t in tokens], np.int64)


def _count_rows(dim: int):
    """(id, counts) of (id, lowered text): hashed's counts of a row; a token's bucket is looked up once while there is room."""

    def rows(batches):
        known: dict[bytes, int] = {}
        for batch in batches:
            counts = np.zeros((batch.num_rows, dim), np.int64)
            for k, text in enumerate(batch.column(1).to_pylist()):
                found = Counter(TOKEN.findall(text.encode())) if text else {}
                new = [t for t in found if t not in known]
                if len(known) + len(new) > KNOWN:
                    known.clear()
                    new = list(found)
                known.update(zip(new, _bucket_of(new, dim).tolist(), strict=True))
                np.add.at(counts[k], [known[t] for t in found], list(found.values()))
            yield pa.RecordBatch.from_arrays([batch.column(0), lists(counts, pa.int64())], names=["id", "counts"])

    return rows


def _unit_rows(batches):
    """(vec_id, embedding) of (id, counts): counts over their norm, all zeros without tokens."""
    for batch in batches:
        n = batch.column(1).flatten().to_numpy().reshape(batch.num_rows, -1)
        norm = np.sqrt((n * n).sum(axis=1).astype(np.float64))
        x = n / np.where(norm > 0, norm, 1.0)[:, None]
        yield pa.RecordBatch.from_arrays([batch.column(0), lists(x.astype(np.float32), pa.float32())], names=["vec_id", "embedding"])


def hashed_vectors(texts: DataFrame, id_col: str, dim: int) -> DataFrame:
    """(vec_id, embedding): hashed counts over their norm; texts without tokens become zero vectors.

    The same counts as hashed's in one pass over the texts; those of an id that
    repeats are the sum over its rows, and a null id has none.
    """
    kind = texts.schema[id_col].dataType.simpleString()
    counted = texts.select(id_col, F.lower("text").alias("text")).mapInArrow(_count_rows(dim), f"id {kind}, counts array<bigint>")
    repeats = texts.groupBy(id_col).count().filter(F.col(id_col).isNull() | (F.col("count") > 1)).select(F.col(id_col).alias("id")).persist()
    if not repeats.isEmpty():
        none = F.array_repeat(F.lit(0).cast("long"), dim)
        again = counted.join(repeats, "id", "left_semi")
        added = again.groupBy("id").agg(F.array(*(F.sum(F.get("counts", F.lit(b))) for b in range(dim))).alias("counts"))
        again = again.drop("counts").join(added, "id")
        nulls = texts.filter(F.col(id_col).isNull()).select(F.col(id_col).alias("id"), none.alias("counts"))
        counted = counted.filter("id IS NOT NULL").join(repeats, "id", "left_anti").unionByName(again).unionByName(nulls)
    repeats.unpersist()
    return counted.mapInArrow(_unit_rows, f"vec_id {kind}, embedding array<float>")


def page_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    bare = F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " "), r"(?s)<[^>]*>", " ")
    return table(spark, sf_dir, "pages").select("page_id", bare.alias("text"))


def conversation_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = F.array_sort(F.collect_list(F.struct("turn", "text")))
    return table(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(turns, lambda s: s.text), " ").alias("text"))


LINE_FEATURES = ("l_quantity / 50", "l_extendedprice / 100000", "l_discount * 10", "l_tax * 10", "month(l_shipdate) / 12.0D", "(dayofweek(l_shipdate) - 1) / 7.0D", "(year(l_shipdate) - 1995) / 10.0D", "l_linenumber / 7.0D")


def line_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight scaled columns of lineitem; its keys repeat, so vec_id numbers nothing in particular."""
    e = F.array(*(F.expr(f).cast("double") for f in LINE_FEATURES))
    return table(spark, sf_dir, "lineitem").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("vec_id"), "l_returnflag", "l_extendedprice", e.alias("embedding"))


def exact_sum(name: str) -> Column:
    """The sum of a column of doubles in any order of rows: of decimals where all values have ten places at most, else of doubles."""
    c = F.col(name)
    exact = c.try_cast("decimal(28,10)")
    other = c.isNotNull() & ~F.coalesce(exact.cast("double") == c, F.lit(False))
    return F.when(F.count_if(other) == 0, F.sum(exact).cast("double")).otherwise(F.sum(c))


def user_hours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per user: shares of 24 hours and of the event types in order of name, and mean, least and greatest value; a mean doesn't depend on the order of rows."""
    events = table(spark, sf_dir, "events")
    kinds = [r[0] for r in events.select("event_type").distinct().orderBy("event_type").collect()]
    hours = [F.count_if(F.hour("ts") == h) / F.count("*") for h in range(24)]
    types = [F.count_if(F.col("event_type") == k) / F.count("*") for k in kinds]
    return events.groupBy(F.col("user_id").alias("vec_id")).agg(F.array(*hours, *types, exact_sum("value") / F.when(F.count("value") > 0, F.count("value")), F.min("value"), F.max("value")).alias("embedding"))


def placed(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table with _place, a long that orders its rows as its files hold them: by the file's name, then by row (2^40 of them at most)."""
    df = table(spark, sf_dir, name)
    files = sorted(r[0] for r in df.select("_metadata.file_path").distinct().collect())
    ranks = spark.createDataFrame(list(enumerate(files)), "_rank long, _file string")
    df = df.withColumns({"_file": F.col("_metadata.file_path"), "_row": F.col("_metadata.row_index")})
    return df.join(F.broadcast(ranks), "_file").withColumn("_place", F.shiftleft("_rank", 40) + F.col("_row")).drop("_file", "_rank", "_row")


def rounded(x: Column, places: int) -> Column:
    """Rounded as SQL's round of doubles does it, on x times ten to the places; Spark's round looks at the decimal digits of x instead."""
    t = x * F.lit(10.0**places)
    return F.when(F.abs(t) < float("inf"), F.round(t) / F.lit(10.0**places)).otherwise(x)


def sums_in_order(df: DataFrame, key: str, *names: str) -> DataFrame:
    """df with the columns named replaced by their running sums within key, by _place: a sum of doubles depends on its order, so that order is the table's."""
    w = Window.partitionBy(key).orderBy("_place").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return df.select(*(F.sum(c).over(w).alias(c) if c in names else F.col(c) for c in df.columns))


def customer_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per customer: orders by month, mean price, quantity and discount of lines, and lines; lines are summed up by order first, all in the order of the tables."""
    end = lambda c: F.max_by(c, "_place")
    lines = placed(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), F.col("l_quantity").alias("q"), F.col("l_discount").alias("d"), "_place")
    lines = sums_in_order(lines, "o_orderkey", "q", "d").groupBy("o_orderkey").agg(end("q").alias("q"), end("d").alias("d"), F.count("*").alias("n"))
    orders = placed(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.month("o_orderdate").alias("month"), F.col("o_totalprice").alias("p"), F.col("o_totalprice").isNotNull().alias("priced"), "_place").join(lines, "o_orderkey", "left")
    months = [F.count_if(F.col("month") == m).cast("double") for m in range(1, 13)]
    n = F.coalesce(F.sum("n"), F.lit(0)).cast("double")
    each = lambda c: F.when(n > 0, end(c) / n).otherwise(0.0)
    price = F.when(F.count_if("priced") > 0, end("p") / F.count_if("priced"))
    return sums_in_order(orders, "o_custkey", "p", "q", "d").groupBy(F.col("o_custkey").alias("vec_id")).agg(F.array(*months, price, each("q"), each("d"), n).alias("embedding"))


def replicate(df: DataFrame, times: int, jitter: float = 0.0) -> DataFrame:
    """Each row times over, ids apart, optionally moved a little by its hash."""
    out = df.withColumn("_r", F.explode(F.sequence(F.lit(0), F.lit(times - 1))))
    moved = F.transform("embedding", lambda x, i: x + F.lit(jitter) * (F.pmod(F.xxhash64("vec_id", "_r", i), F.lit(1001)) / 1000.0 - 0.5)) if jitter else F.col("embedding")
    return out.withColumn("embedding", moved).withColumn("vec_id", F.col("vec_id") * times + F.col("_r")).drop("_r")


def collection(name: str, spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    """A collection by name: emb64, emb_ladder, doc_hash, page_hash, conv_hash, line_feat, user_hours, cust_profile."""
    if name == "emb64":
        return table(spark, sf_dir, "embeddings")
    if name == "emb_ladder":
        return ladder(spark, sf_dir, options.get("dim", 128), whole=True)
    if name == "doc_hash":
        return hashed_vectors(table(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id", options.get("dim", 256))
    if name == "page_hash":
        return hashed_vectors(page_texts(spark, sf_dir), "page_id", options.get("dim", 256))
    if name == "conv_hash":
        return hashed_vectors(conversation_texts(spark, sf_dir), "conv_id", options.get("dim", 128))
    found = {"line_feat": line_features, "user_hours": user_hours, "cust_profile": customer_profile}
    return found[name](spark, sf_dir)
