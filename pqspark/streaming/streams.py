"""Structured Streaming: continuous encoding, drift, deduplication, upserts and running code counts."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StreamingQuery

from pqspark.model import PQModel
from pqspark.operators import encode, layout

VECTOR_SCHEMA = "vec_id long, embedding array<float>, label int"


def read(spark: SparkSession, path: str, schema: str = VECTOR_SCHEMA, files: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream, files of them in a batch."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def encoded(stream: DataFrame, model: PQModel, keep: tuple[str, ...] = ()) -> DataFrame:
    """The batch plan on a stream: one narrow pass, tagged with the model."""
    return encode.encode(stream, model, keep=keep).withColumn("model_id", F.lit(model.model_id))


def errors(df: DataFrame, model: PQModel, vector: str = "embedding", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, kept, sse): the squared error of each row's code, without a join, for streams."""
    encoded_ = encode.encode(df, model, vector=vector, keep=(*keep, vector + "_copy") if vector + "_copy" in df.columns else keep)
    books = F.array(*(F.array(*(F.array(*(F.lit(float(x)) for x in c)) for c in b)) for b in model.books))
    pieces = F.array(*layout.pieces(model.config, vector + "_copy"))
    gap = F.zip_with(F.zip_with(pieces, "codes", lambda p, c: F.struct(p.alias("p"), c.alias("c"))), books, lambda s, b: layout.squared(s.p, F.get(b, s.c.cast("int"))))
    return encoded_.withColumn("sse", F.aggregate(gap, F.lit(0.0), lambda a, x: a + x)).drop("codes", vector + "_copy")


def drift(df: DataFrame, ts: str = "ts", window: str = "1 day", late: str = "1 hour") -> DataFrame:
    """(window start, rows, mean error) of rows(ts, sse) in tumbling windows; rows past the watermark are dropped."""
    w = F.window(ts, window)
    return df.withWatermark(ts, late).groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.avg("sse").alias("mean_sse")).select(F.col("w.start").alias("start"), "n", "mean_sse")


def sessions(df: DataFrame, ts: str = "ts", gap: str = "30 minutes", late: str = "1 hour", by: str = "user_id") -> DataFrame:
    s = F.session_window(ts, gap)
    return df.withWatermark(ts, late).groupBy(by, s.alias("s")).agg(F.count("*").alias("n")).select(by, F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n")


def dedupe(df: DataFrame, ts: str = "ts", horizon: str = "1 day", key: str = "vec_id") -> DataFrame:
    """The first row of each id within the horizon."""
    return df.withWatermark(ts, horizon).dropDuplicatesWithinWatermark([key])


def last_operation(changes: DataFrame) -> DataFrame:
    """changes(vec_id, ts, seq, op, ...) with only each id's last one."""
    from pyspark.sql.window import Window

    r = F.row_number().over(Window.partitionBy("vec_id").orderBy(F.desc("ts"), F.desc("seq")))
    return changes.withColumn("_r", r).filter("_r = 1").drop("_r")


def upsert(stream: DataFrame, model: PQModel, path: str, checkpoint: str) -> StreamingQuery:
    """Keep the codes table under path current: batch n reads version n-1 and writes version n, so a repeated batch writes the same."""

    def apply(batch: DataFrame, epoch: int) -> None:
        spark = batch.sparkSession
        last = last_operation(batch).persist()
        new = encode.encode(last.filter("op = 'upsert'"), model).withColumn("model_id", F.lit(model.model_id))
        if epoch > 0:
            old = spark.read.parquet(f"{path}/v={epoch - 1}")
            new = old.join(last.select("vec_id"), "vec_id", "left_anti").unionByName(new)
        new.write.mode("overwrite").parquet(f"{path}/v={epoch}")
        last.unpersist()

    return stream.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def settled(results: DataFrame, path: str, keys: list[str], mode: str = "update") -> DataFrame:
    """Run a stream to the end of its input; the last row written for each key.

    Batch n writes its own folder, so a repeated batch writes the same. In complete mode the last batch is the whole result.
    """

    def store(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/out/v={epoch}")

    results.writeStream.foreachBatch(store).outputMode(mode).option("checkpointLocation", f"{path}/log").trigger(availableNow=True).start().awaitTermination()
    made = results.sparkSession.read.schema(T.StructType([*results.schema.fields, T.StructField("v", T.IntegerType())])).parquet(f"{path}/out")
    if mode == "complete":
        return made.filter(F.col("v") == made.agg(F.max("v")).first()[0]).drop("v")
    if mode == "append":
        return made.drop("v")
    others = [c for c in made.columns if c not in (*keys, "v")]
    return made.groupBy(*keys).agg(F.max_by(F.struct(*others), "v").alias("_last")).select(*keys, "_last.*")


def with_static(stream: DataFrame, static: DataFrame, key: str) -> DataFrame:
    """The stream's rows with the columns of a static table; no state is kept."""
    return stream.join(static, key)


def near_in_time(left: DataFrame, right: DataFrame, key: str, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Pairs of two streams' rows of equal key whose times, ts and ts_right, lie within a span; older rows leave the state by the watermark."""
    a, b = left.withWatermark("ts", late), right.withWatermark("ts_right", late)
    span = F.expr(f"ts BETWEEN ts_right - INTERVAL {within} AND ts_right + INTERVAL {within}")
    return a.join(b.withColumnRenamed(key, "_key"), (F.col(key) == F.col("_key")) & span).drop("_key")


def running_counts(codes: DataFrame) -> DataFrame:
    """(chunk, code, n) of a stream of codes, counted on in per-chunk state."""

    def count(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        held = dict(zip(*state.get, strict=True)) if state.exists else {}
        for batch in batches:
            for code, n in batch["code"].value_counts().items():
                held[int(code)] = held.get(int(code), 0) + int(n)
        state.update((list(held), list(held.values())))
        yield pd.DataFrame({"chunk": [key[0]] * len(held), "code": list(held), "n": list(held.values())})

    each = codes.select(F.posexplode("codes").alias("chunk", "code")).withColumn("code", F.col("code").cast("int"))
    return each.groupBy("chunk").applyInPandasWithState(count, "chunk int, code int, n long", "codes array<int>, ns array<bigint>", "update", "NoTimeout")
