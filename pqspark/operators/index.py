"""Around the codes: coarse lists, neighbour graphs built by block, beam search, maintenance, the build pipeline."""

from __future__ import annotations

import bisect
import time
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pqspark.model import PQConfig, PQModel
from pqspark.operators import encode, search, train


def knn_graph(df: DataFrame, k: int, dim: int = 64) -> DataFrame:
    """(src, rank, dst, dist): exact, for small collections."""
    return search.exact(df, df, k, dim).select(F.col("query_id").alias("src"), "rank", F.col("vec_id").alias("dst"), "dist")


def coarse(df: DataFrame, nlist: int, iterations: int = 5, init: str = "hash", dim: int = 64) -> tuple[PQModel, DataFrame]:
    """A partition of whole vectors: the model has one chunk, and rows get the list of their centroid."""
    model = train.lloyd(df, PQConfig(dim=dim, width=dim, k=nlist, iterations=iterations, init=init))
    return model, encode.encode(df, model).select("vec_id", F.get("codes", F.lit(0)).cast("int").alias("list"))


def probes(queries: DataFrame, model: PQModel, nprobe: int) -> DataFrame:
    """(query_id, list): each query's nearest lists."""
    scored = encode.scored_rows(queries, model)
    nearest = F.slice(F.array_sort(F.collect_list(F.struct("score", "centroid"))), 1, nprobe)
    return scored.groupBy(F.col("vec_id").alias("query_id")).agg(F.transform(nearest, lambda s: s.centroid.cast("int")).alias("lists")).select("query_id", F.explode("lists").alias("list"))


def pruned(x: np.ndarray, point: int, candidates: list[tuple[float, int]], degree: int, alpha: float) -> list[int]:
    """Nearest first; one that a kept neighbour is closer to, by the factor, is left out."""
    ordered = [(dist, c) for dist, c in sorted(candidates) if c != point]
    if not ordered:
        return []
    ids = [c for _, c in ordered]
    dists, rows = np.array([dist for dist, _ in ordered]), x[ids]
    # few candidates are compared all at once, many with each one that is kept
    all_apart = alpha * ((rows[:, None] - rows) ** 2).sum(axis=-1) > dists if len(ids) <= 24 else None
    left = np.ones(len(ids), bool)
    kept: list[int] = []
    at = 0
    while len(kept) < degree:
        at += int(left[at:].argmax())
        if not left[at]:
            break
        kept.append(ids[at])
        left &= all_apart[at] if all_apart is not None else alpha * ((rows - rows[at]) ** 2).sum(axis=1) > dists
        left[at] = False
    return kept


def block_graph(ids: np.ndarray, x: np.ndarray, degree: int, pool: int, alpha: float) -> list[tuple[int, int, float]]:
    """Edges (src, dst, dist) of one block: rows are inserted in order of hash, linked to what a greedy search visits, and pruned."""
    n = len(x)
    if n < 2:
        return []
    start = int(((x - x.mean(axis=0)) ** 2).sum(axis=1).argmin())
    links: list[list[int]] = [[] for _ in range(n)]
    order = np.argsort((ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(11), kind="stable")
    for p in order.tolist():
        if p == start:
            continue
        near = [(float(((x[start] - x[p]) ** 2).sum()), start)]  # the pool nearest of those seen, sorted
        seen = {start, p}
        visited: dict[int, float] = {}
        at = 0
        while at < len(near):  # all before at are visited
            dist, c = near[at]
            at += 1
            if c in visited:
                continue
            visited[c] = dist
            new = [q for q in links[c] if q not in seen]
            if new:
                seen.update(new)
                for found in zip(((x[new] - x[p]) ** 2).sum(axis=1).tolist(), new, strict=True):
                    if len(near) < pool or found < near[-1]:
                        to = bisect.bisect(near, found)
                        near.insert(to, found)
                        del near[pool:]
                        at = min(at, to)
        links[p] = pruned(x, p, [(dist, c) for c, dist in visited.items()], degree, alpha)
        for q in links[p]:
            if p not in links[q]:
                links[q].append(p)
                if len(links[q]) > degree:
                    links[q] = pruned(x, q, list(zip(((x[links[q]] - x[q]) ** 2).sum(axis=1).tolist(), links[q], strict=True)), degree, alpha)
    return [(int(ids[a]), int(ids[b]), float(((x[a] - x[b]) ** 2).sum())) for a in range(n) for b in links[a]]


def build_graph(df: DataFrame, degree: int = 64, pool: int = 128, alpha: float = 1.2, block_rows: int = 2000, dim: int = 64) -> DataFrame:
    """(vec_id, neighbors, dists): rows go to the blocks of their two nearest centres, blocks build apart, and edges are merged and cut to degree."""
    blocks = max(1, -(-df.count() // block_rows))
    if blocks == 1:
        placed = df.select("vec_id", "embedding", F.lit(0).alias("block"))
    else:
        model = train.lloyd(df, PQConfig(dim=dim, width=dim, k=blocks, iterations=5))
        near = encode.scored_rows(df, model).withColumn("r", F.row_number().over(Window.partitionBy("vec_id").orderBy("score", "centroid"))).filter("r <= 2")
        placed = near.select("vec_id", F.col("centroid").alias("block")).join(df.select("vec_id", "embedding"), "vec_id")

    def build(table: pa.Table) -> pa.Table:
        x = np.array(table.column("embedding").to_pylist(), np.float64)
        got = block_graph(table.column("vec_id").to_numpy(), x, degree, pool, alpha)
        return pa.table({name: pa.array([e[k] for e in got], kind) for k, (name, kind) in enumerate((("src", pa.int64()), ("dst", pa.int64()), ("dist", pa.float64())))})

    edges = placed.groupBy("block").applyInArrow(build, "src long, dst long, dist double").distinct()
    rank = F.row_number().over(Window.partitionBy("src").orderBy("dist", "dst"))
    best = edges.withColumn("rank", rank).filter(F.col("rank") <= degree)
    sorted_ = F.array_sort(F.collect_list(F.struct("rank", "dst", "dist")))
    return best.groupBy(F.col("src").alias("vec_id")).agg(F.transform(sorted_, lambda s: s.dst).alias("neighbors"), F.transform(sorted_, lambda s: s.dist.cast("float")).alias("dists"))


def beam(queries: DataFrame, graph: DataFrame, codes: DataFrame, model: PQModel, base: DataFrame, entries: list[int], width: int = 64, k: int = 10, hops: int = 12, expand: int = 8) -> DataFrame:
    """Graph search on code distances, all queries at once: each hop expands the best unexpanded of every query, then exact re-ranking."""
    spark = codes.sparkSession
    graph, codes = graph.persist(), codes.persist()  # every hop reads both
    luts = search.lut(queries, model)
    asked = F.broadcast(luts.groupBy("query_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("chunk", "lut"))), lambda s: s.lut).alias("luts")).persist())
    distance = F.aggregate(F.zip_with("luts", "codes", lambda t, c: F.get(t, c.cast("int"))), F.lit(0.0), lambda s, d: s + d)
    near = lambda pairs: pairs.join(codes.select("vec_id", "codes"), "vec_id").join(asked, "query_id").select("query_id", "vec_id", distance.alias("dist"))
    start = spark.createDataFrame([(e,) for e in entries], "vec_id long")
    held = near(queries.select(F.col("vec_id").alias("query_id")).crossJoin(F.broadcast(start))).withColumn("done", F.lit(False))
    order = Window.partitionBy("query_id").orderBy("dist", "vec_id")
    for _ in range(hops):
        held = held.persist()
        if spark.sparkContext.getCheckpointDir():
            computed, held = held, held.checkpoint()  # writes what the first pass has kept
            computed.unpersist()
        ahead = held.filter("NOT done").withColumn("r", F.row_number().over(order)).filter(F.col("r") <= expand).select("query_id", "vec_id")
        if ahead.isEmpty():
            break
        reached = ahead.join(graph, "vec_id").select("query_id", F.explode("neighbors").alias("vec_id")).distinct().join(held, ["query_id", "vec_id"], "left_anti")
        marked = held.join(ahead.withColumn("now", F.lit(True)), ["query_id", "vec_id"], "left").select("query_id", "vec_id", "dist", (F.col("done") | F.coalesce("now", F.lit(False))).alias("done"))
        held = marked.unionByName(near(reached).withColumn("done", F.lit(False))).withColumn("r", F.row_number().over(order)).filter(F.col("r") <= width).drop("r")
    return search.rerank(held.filter("query_id <> vec_id"), queries, base, k)


def insert(encoded: DataFrame, new: DataFrame, model: PQModel) -> DataFrame:
    """encoded(vec_id, codes, model_id) with new rows encoded; rows of the same id are replaced."""
    made = encode.encode(new, model).withColumn("model_id", F.lit(model.model_id))
    return encoded.join(made.select("vec_id"), "vec_id", "left_anti").unionByName(made)


def delete(encoded: DataFrame, gone: DataFrame) -> DataFrame:
    return encoded.join(gone.select("vec_id"), "vec_id", "left_anti")


def build(df: DataFrame, config: PQConfig, strategy: str = "staged", graph: bool = True, degree: int = 16, pool: int = 32) -> tuple[PQModel, DataFrame, DataFrame | None, dict[str, float]]:
    """Train, encode, link: (model, codes, graph, seconds by stage); only the two first stages depend on the strategy."""
    took, t = {}, time.perf_counter()
    model = train.lloyd(df, config, score="expanded" if strategy == "expanded" else "ranking")
    took["train"], t = time.perf_counter() - t, time.perf_counter()
    codes = encode.encode(df, model, strategy)
    codes.write.format("noop").mode("overwrite").save()
    took["encode"], t = time.perf_counter() - t, time.perf_counter()
    links = build_graph(df, degree, pool, dim=config.dim) if graph else None
    if links is not None:
        links.write.format("noop").mode("overwrite").save()
    took["graph"] = time.perf_counter() - t
    return model, codes, links, took


def with_width(config: PQConfig, width: int) -> PQConfig:
    return replace(config, width=width)
