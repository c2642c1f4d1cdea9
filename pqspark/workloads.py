"""The experiments on the given tables, as measurements; and the measures that they report."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pqspark.model import PQConfig
from pqspark.operators import encode, index, search, train, vectors
from pqspark.plans import cost

MEASURED = "workload string, variant string, metric string, value double, params map<string,string>"
#: The cumulative steps of the ablation: strategy and its options.
LADDER = {
    "baseline": ("lane_by_dimension", {}),
    "+lanes": ("tiled", {"score": "full", "order": "row_major"}),
    "+order": ("tiled", {"score": "expanded", "order": "block_chunk"}),
    "+score": ("staged", {}),
}


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """(n_rows, equal, missing_a, missing_b) of two code tables."""
    both = a.select("vec_id", F.col("codes").alias("a")).join(b.select("vec_id", F.col("codes").alias("b")), "vec_id", "full")
    return both.agg(F.count("*").alias("n_rows"), F.count_if(F.col("a").eqNullSafe(F.col("b"))).alias("equal"), F.count_if(F.col("a").isNull()).alias("missing_a"), F.count_if(F.col("b").isNull()).alias("missing_b"))


def usage(codes: DataFrame) -> DataFrame:
    """(chunk, used, entropy, max_share) of a code table."""
    counts = codes.select(F.posexplode("codes").alias("chunk", "code")).groupBy("chunk", "code").agg(F.count("*").alias("n"))
    total = codes.agg(F.count("*").cast("double").alias("t"))
    share = counts.crossJoin(F.broadcast(total)).withColumn("p", F.col("n") / F.col("t"))
    return share.groupBy("chunk").agg(F.count("*").alias("used"), F.round(-F.sum(F.col("p") * F.log2("p")), 6).alias("entropy"), F.round(F.max("p"), 6).alias("max_share"))


def timed(run: Callable[[], DataFrame], runs: int = 3, warmup: int = 1) -> list[float]:
    """Seconds of full evaluations into a sink that keeps nothing."""
    took = []
    for k in range(warmup + runs):
        t = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        if k >= warmup:
            took.append(time.perf_counter() - t)
    return took


def speedup(measured: DataFrame, base: str, metric: str = "pq_s") -> DataFrame:
    """(workload, params, variant, seconds, speedup, reduction) against the base variant; seconds are means over the runs."""
    keyed = measured.filter(F.col("metric") == metric).withColumn("params", F.to_json("params"))
    seconds = keyed.groupBy("workload", "params", "variant").agg(F.avg("value").alias("seconds"))
    ref = seconds.filter(F.col("variant") == base).select("workload", "params", F.col("seconds").alias("ref"))
    out = seconds.join(ref, ["workload", "params"])
    return out.select("workload", "params", "variant", "seconds", (F.col("ref") / F.col("seconds")).alias("speedup"), (1 - F.col("seconds") / F.col("ref")).alias("reduction"))


#: Rows that a measurement needs, at least, for its seconds to be those of the kernel; smaller collections are replicated with jitter.
ENOUGH, PLENTY = 10_000, 100_000
#: Runs after a warm-up that a mean is taken of.
RUNS = 5


def _rows(spark: SparkSession, sf_dir: str, name: str, least: int = 0, **options) -> tuple[DataFrame, int]:
    """A collection, kept in memory and dealt evenly, and its dimensions."""
    df = vectors.collection(name, spark, sf_dir, **options).select("vec_id", "embedding")
    if least:
        even = lambda rows: rows.repartition(spark.sparkContext.defaultParallelism).persist()
        df = few = even(df)
        n = max(1, df.count())  # of what is kept: a collection is made once
        if n < least:
            df = even(vectors.replicate(few, -(-least // n), 0.01))
            df.count()
            few.unpersist()
    else:
        df = df.persist()
    first = df.select(F.size("embedding").alias("n")).first()
    return df, first.n if first else 0


def _measure(workload: str, df: DataFrame, config: PQConfig, variants: dict, params: dict, runs: int = 3) -> list[tuple]:
    """Training and encoding time, share of equal codes, and counted work of each variant on one trained model.

    A variant trains with its own kernel; pq_s is that and the mean of its encoding runs.  The codes that are compared are
    the variant's warm-up.
    """
    model = train.lloyd(df, config)  # also the warm-up
    want = encode.encode(df, model).persist()
    n = df.count()
    out = []
    for variant, (strategy, options) in variants.items():
        t = time.perf_counter()
        own = train.lloyd(df, config, kernel=(strategy, options)) if strategy != "scalar_udf" else model
        train_s = time.perf_counter() - t
        run = lambda strategy=strategy, options=options: encode.encode(df, model, strategy, **options)
        same = agreement(want, run()).first()
        took = timed(run, runs, warmup=0)
        out += [(workload, variant, "encode_s", seconds, params) for seconds in took]
        out.append((workload, variant, "train_s", train_s, params))
        out.append((workload, variant, "pq_s", train_s + sum(took) / len(took), params))
        out.append((workload, variant, "rows_per_s", n * len(took) / sum(took), params))
        out.append((workload, variant, "model_gap", model.diff(own), params))
        out.append((workload, variant, "agreement", same.equal / max(1, same.n_rows), params))
        counted = {"lane_by_dimension": "lane_by_dimension", "expanded": "expanded", "staged": "staged", "matrix": "matrix"}.get(strategy, "tiled_full")
        out.append((workload, variant, "operations", float(cost.counters(n, config.dim, config.chunks, config.k, counted)["arithmetic"]), params))
    want.unpersist()
    return out


#: The baselines of the timed comparisons and the staged engine.
AGAINST = {"lane_by_dimension": ("lane_by_dimension", {}), "matrix": ("matrix", {}), "expanded": ("expanded", {}), "staged": ("staged", {})}


def w1_index_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Build time by code size, and the quantizer's share of it; the graph is of the vectors and free of the code size, so it is built once."""
    df, dim = _rows(spark, sf_dir, "emb64")
    out, graph_s = [], None
    for width in (32, 16, 8, 4):
        config = PQConfig(dim=dim, width=width, iterations=3)
        _, _, _, took = index.build(df, config, graph=graph_s is None)
        graph_s = took["graph"] = took["graph"] if graph_s is None else graph_s
        p = {"bits": str(config.chunks * config.bits)}
        out += [("w1", "staged", f"{stage}_s", t, p) for stage, t in took.items()]
        out.append(("w1", "staged", "share", (took["train"] + took["encode"]) / sum(took.values()), p))
    df.unpersist()
    return spark.createDataFrame(out, MEASURED)


def w2_throughput(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidates and queries a second at a recall of 0.95, by code size and corpus size."""
    out = []
    for times in (1, 10):
        df = vectors.replicate(vectors.collection("emb64", spark, sf_dir).select("vec_id", "embedding"), times, 0.05).persist()
        q = df.filter("vec_id % 20 = 0")
        truth = search.exact(q, df).persist()
        for width in (8, 4, 2):
            model = train.lloyd(df, PQConfig(width=width, k=16, iterations=3))
            codes = encode.encode(df, model).persist()
            codes.count()
            need = search.needed(q, codes, model, truth, 10, 0.95)
            t = time.perf_counter()
            search.rerank(search.adc(q, codes, model, need), q, df).count()
            p = {"bits": str(64 // width * 4), "times": str(times)}
            out += [("w2", "staged", "candidates", float(need), p), ("w2", "staged", "queries_per_s", q.count() / (time.perf_counter() - t), p)]
            codes.unpersist()
        truth.unpersist()
        df.unpersist()
    return spark.createDataFrame(out, MEASURED)


#: Every collection, with its options and the width of its pieces.
ALL_SETS = (
    ("emb64", {}, 16),
    ("emb_ladder", {"dim": 128}, 16),
    ("doc_hash", {"dim": 256}, 16),
    ("page_hash", {"dim": 256}, 16),
    ("conv_hash", {"dim": 128}, 16),
    ("line_feat", {}, 8),
    ("cust_profile", {}, 16),
    ("user_hours", {}, 8),
)


def w3_all_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Baseline against the staged engine on every collection."""
    out = []
    for name, options, width in ALL_SETS:
        df, dim = _rows(spark, sf_dir, name, ENOUGH, **options)
        config = PQConfig(dim=dim, width=width, iterations=2, split="even" if dim % width == 0 else "pad")
        out += _measure("w3", df, config, AGAINST, {"set": name, "dim": str(dim)})
        df.unpersist()
    return spark.createDataFrame(out, MEASURED)


def w4_tradeoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Build time against recall over code sizes, for both strategies."""
    df, dim = _rows(spark, sf_dir, "emb64")
    q = df.filter("vec_id % 20 = 0")
    truth = search.exact(q, df).persist()
    out = []
    for width in (16, 8, 4, 2):
        for strategy in ("expanded", "staged"):
            model, codes, _, took = index.build(df, PQConfig(dim=dim, width=width, iterations=3), strategy, graph=False)
            found = search.rerank(search.adc(q, codes, model, 100), q, df)
            r = search.recall(found, truth, 10).agg(F.avg("recall")).first()[0]
            p = {"bits": str(64 // width * 8)}
            out += [("w4", strategy, "build_s", sum(took.values()), p), ("w4", strategy, "recall", float(r), p)]
    return spark.createDataFrame(out, MEASURED)


def _sweep(workload: str, sets: tuple, configs: Callable[[int], list[PQConfig]], label: Callable[[PQConfig], dict]) -> Callable:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = []
        for name, options in sets:
            df, dim = _rows(spark, sf_dir, name, ENOUGH, **options)
            for config in configs(dim):
                out += _measure(workload, df, config, AGAINST, {"set": name, **label(config)})
            df.unpersist()
        return spark.createDataFrame(out, MEASURED)

    return run


w5_code_size = _sweep("w5", (("emb64", {}), ("doc_hash", {"dim": 256})), lambda dim: [PQConfig(dim=dim, width=w, iterations=1) for w in (32, 16, 8, 4)], lambda c: {"chunks": str(c.chunks)})
w6_codebook_size = _sweep("w6", (("emb64", {}), ("doc_hash", {"dim": 256})), lambda dim: [PQConfig(dim=dim, width=16, k=k, iterations=1) for k in (16, 64, 256, 1024)], lambda c: {"k": str(c.k)})
w7_dimension = _sweep("w7", tuple(("emb_ladder", {"dim": n}) for n in (128, 192, 256)), lambda dim: [PQConfig(dim=dim, width=16, iterations=1)], lambda c: {"dim": str(c.dim)})


def w8_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each component added in turn."""
    out = []
    for name, options in (("emb_ladder", {"dim": 256}), ("doc_hash", {"dim": 256}), ("emb64", {})):
        df, dim = _rows(spark, sf_dir, name, PLENTY, **options)
        out += _measure("w8", df, PQConfig(dim=dim, width=16, iterations=1), LADDER, {"set": name}, RUNS if dim < 100 else 2)
        df.unpersist()
    return spark.createDataFrame(out, MEASURED)


def w9_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stand-ins for hardware counters: what the system counts for the kernels, beside counted operations and live score bytes."""
    df, dim = _rows(spark, sf_dir, "emb_ladder", ENOUGH, dim=256)
    config = PQConfig(dim=dim, width=16, iterations=1)
    model, n = train.lloyd(df, config), df.count()
    out = []
    for strategy in ("lane_by_dimension", "matrix", "expanded", "staged"):
        told = encode.profiled(df, model, strategy).agg(F.sum("cpu_s").alias("cpu_s"), F.sum("faults").alias("page_faults"), F.sum("switches").alias("context_switches"), F.max("peak_mb").alias("peak_mb")).first().asDict()
        out += [("w9", strategy, name, float(v), {"set": "emb_ladder"}) for name, v in told.items()]
        out += [("w9", strategy, name, float(v), {"set": "emb_ladder"}) for name, v in cost.counters(n, dim, config.chunks, config.k, strategy).items() if name in ("arithmetic", "live_score_bytes", "codebook_switches")]
    df.unpersist()
    return spark.createDataFrame(out, MEASURED)


def w10_defaults(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of codes with the defaults, by one vector of embeddings after another joined to long ones of 256 and of 1024 dimensions or so."""
    out = []
    for times in (4, 16):
        e = vectors.table(spark, sf_dir, "embeddings").filter("embedding IS NOT NULL")
        joined = e.groupBy(F.floor(F.col("vec_id") / times).alias("id")).agg(F.sum(F.size("embedding")).alias("dim"), F.count("*").alias("parts")).filter(F.col("parts") == times)
        for dim, n in joined.groupBy("dim").agg(F.count("*").alias("n")).orderBy("dim").collect():
            _, size, ratio = cost.sizes(dim, -(-dim // 16), 8)
            p = {"dim": str(dim)}
            out += [("w10", "default", "bytes", float(size), p), ("w10", "default", "ratio", ratio, p), ("w10", "default", "table_bytes", float(n * size), p)]
    return spark.createDataFrame(out, MEASURED)


def w12_width(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall, distortion and use of lanes by the width of a piece."""
    df, dim = _rows(spark, sf_dir, "emb64")
    q = df.filter("vec_id % 20 = 0")
    truth = search.exact(q, df).persist()
    out = []
    for width in (32, 16, 8, 4, 2):
        model = train.lloyd(df, PQConfig(dim=dim, width=width, k=16, iterations=5))
        codes = encode.encode(df, model)
        r = search.recall(search.adc(q, codes, model, 10), truth, 10).agg(F.avg("recall")).first()[0]
        mse = encode.distortion(df, codes, model).agg(F.sum("mse")).first()[0]
        p = {"width": str(width)}
        out += [("w12", "staged", "recall", float(r), p), ("w12", "staged", "distortion", float(mse), p), ("w12", "lane_by_dimension", "lanes", cost.lane_use(width, 16, 16)[0], p)]
    return spark.createDataFrame(out, MEASURED)


def w13_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Time and live bytes by block size."""
    df, dim = _rows(spark, sf_dir, "doc_hash", ENOUGH, dim=256)
    variants = {f"block {b}": ("staged", {"block_rows": b}) for b in (256, 1024, 4096, 1 << 20)}
    return spark.createDataFrame(_measure("w13", df, PQConfig(dim=dim, width=16, iterations=1), variants, {}), MEASURED)


def w14_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All scores give the same codes."""
    df, dim = _rows(spark, sf_dir, "emb64")
    variants = {score: ("tiled", {"score": score}) for score in ("full", "expanded", "ranking", "ranking2")} | {"ranking f32": ("staged", {"precision": "f32"})}
    return spark.createDataFrame(_measure("w14", df, PQConfig(dim=dim, width=16, k=16, iterations=2), variants, {}), MEASURED)


def transfer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The offload analogue: rows that cross the process border one by one against batches."""
    df, dim = _rows(spark, sf_dir, "emb64")
    return spark.createDataFrame(_measure("transfer", df, PQConfig(dim=dim, width=16, k=16, iterations=1), {"row by row": ("scalar_udf", {}), "batches": ("staged", {})}, {}), MEASURED)


def queries() -> dict:
    return {
        "w1_index_time": w1_index_time,
        "w2_throughput": w2_throughput,
        "w3_all_sets": w3_all_sets,
        "w4_tradeoff": w4_tradeoff,
        "w5_code_size": w5_code_size,
        "w6_codebook_size": w6_codebook_size,
        "w7_dimension": w7_dimension,
        "ablation_ladder": w8_ablation,
        "w9_counters": w9_counters,
        "w10_defaults": w10_defaults,
        "w12_width": w12_width,
        "w13_blocks": w13_blocks,
        "w14_scores": w14_scores,
        "transfer_model": transfer,
    }
