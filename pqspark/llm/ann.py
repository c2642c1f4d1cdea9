"""Approximate nearest neighbours by cross-polytope hashing.

A unit vector is turned by a pseudo-rotation (three rounds of random signs and a
fast Hadamard transform) and hashed to the signed axis that it is nearest to.  Two
rotations make a table, whose buckets are pairs of axes.  A query looks into the
buckets of all tables that its own turned vectors point to most (multiprobe), and
the rows found there are ranked by their exact cosine.

Tables are dealt over the cluster by their first axis: rows and the queries that
probe them meet there, bucket by bucket, and only the best few of a query leave.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pqspark.llm.common import matched, often, partitions, stored

#: Tables, buckets probed in all of them by a query (of tables * (2 * dimensions)**2), and queries compared with every row at once.
TABLES, PROBES, QUERIES = 24, 4096, 4096
#: Axes of each rotation that a query may probe: those that it points to most.
NEAR_AXES = 128
#: Numbers that a task holds of rows, and of queries of one first axis, at a time.
HELD = 4_000_000


class Rotations:
    """Two pseudo-rotations for each table of vectors with dim numbers, padded to a power of two."""

    def __init__(self, dim: int, tables: int = TABLES, seed: int = 7):
        self.size = 1 << max(0, (dim - 1).bit_length())
        draws = np.random.Generator(np.random.PCG64(seed))
        self.signs = draws.integers(0, 2, (2 * tables, 3, self.size)).astype(np.float32) * 2 - 1

    def turned(self, unit: np.ndarray, rotation: int) -> np.ndarray:
        x = np.zeros((len(unit), self.size), np.float32)
        x[:, : unit.shape[1]] = unit
        for signs in self.signs[rotation]:
            x *= signs
            x = hadamard(x)
        return x

    def axes(self, unit: np.ndarray, rotation: int) -> np.ndarray:
        """The nearest signed axis of each row: k for +k, size + k for -k."""
        x = self.turned(unit, rotation)
        k = np.abs(x).argmax(axis=1)
        return k + self.size * (x[np.arange(len(x)), k] < 0)

    def probes(self, unit: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, table, bucket) of the n buckets of each row, over all tables, whose two axes it points to most together."""
        tables, axes = len(self.signs) // 2, 2 * self.size
        near, n_near = [], min(NEAR_AXES, axes)
        for r in range(2 * tables):
            x = self.turned(unit, r)
            reach = np.concatenate([x, -x], axis=1)
            at = np.argpartition(-reach, n_near - 1, axis=1)[:, :n_near]
            near.append((at, np.take_along_axis(reach, at, axis=1)))
        n = min(n, tables * n_near * n_near)
        table, bucket = np.empty((len(unit), n), np.int64), np.empty((len(unit), n), np.int64)
        for k in range(len(unit)):
            both = np.concatenate([(near[r][1][k][:, None] + near[r + 1][1][k]).ravel() for r in range(0, 2 * tables, 2)])
            found = np.argpartition(-both, n - 1)[:n]
            table[k], at = np.divmod(found, n_near * n_near)
            first, second = np.divmod(at, n_near)
            for t in range(tables):
                mine = table[k] == t
                bucket[k, mine] = near[2 * t][0][k][first[mine]] * axes + near[2 * t + 1][0][k][second[mine]]
        return np.repeat(np.arange(len(unit)), n), table.ravel(), bucket.ravel()


def hadamard(x: np.ndarray) -> np.ndarray:
    """Fast Walsh-Hadamard transform of the rows, scaled to keep lengths."""
    n, h = x.shape[1], 1
    while h < n:
        x = x.reshape(len(x), n // (2 * h), 2, h)
        x = np.stack([x[:, :, 0] + x[:, :, 1], x[:, :, 0] - x[:, :, 1]], axis=2).reshape(len(x), n)
        h *= 2
    return x / np.float32(np.sqrt(n))


def usable(vector: str) -> Column:
    """Whether a vector takes part: not null or empty, no null or non-finite component, not zero."""
    v = F.col(vector)
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return v.isNotNull() & (F.size(v) > 0) & ~F.coalesce(bad, F.lit(True)) & F.exists(v, lambda x: x != 0)


def _matrices(batch: pa.RecordBatch) -> list[tuple[np.ndarray, np.ndarray]]:
    """(ids, double matrix) for each vector length in a batch of (id, vector)."""
    ids, vectors = batch.column(0).to_numpy(zero_copy_only=False), batch.column(1)
    flat = vectors.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    length = vectors.value_lengths().to_numpy(zero_copy_only=False)
    first = np.cumsum(length) - length
    return [(ids[rows := np.flatnonzero(length == d)], flat[first[rows][:, None] + np.arange(d)]) for d in np.unique(length)]


def _norms(x: np.ndarray) -> np.ndarray:
    return np.sqrt((x * x).sum(axis=1))


def best(ids: np.ndarray, x: np.ndarray, norm: np.ndarray, q: np.ndarray, q_norm: float, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids, cosines) of the k rows nearest to one query, ties to smaller ids; sums in the same order for equal vectors."""
    if len(ids) > 4 * k:
        rough = (x @ q) / norm
        at = np.flatnonzero(rough >= np.partition(rough, len(rough) - k)[len(rough) - k] - 1e-9 * q_norm)  # whatever the product's rounding
        ids, x, norm = ids[at], x[at], norm[at]
    score = (x * q).sum(axis=1) / (norm * q_norm)
    order = np.lexsort((ids, -score))[:k]
    return ids[order], score[order]


class Best:
    """The k best rows so far of each query of a group."""

    def __init__(self, ids: np.ndarray, q: np.ndarray, k: int):
        self.ids, self.q, self.k, self.norm = ids, q, k, _norms(q)
        self.held: list[tuple[np.ndarray, np.ndarray]] = [(np.zeros(0, np.int64), np.zeros(0))] * len(ids)

    def add(self, query: int, ids: np.ndarray, x: np.ndarray, norm: np.ndarray) -> None:
        got, score = best(ids, x, norm, self.q[query], self.norm[query], self.k)
        old, old_score = self.held[query]
        if len(old):
            both, first = np.unique(np.concatenate([old, got]), return_index=True)  # a row may lie in several tables of a task
            got, score = both, np.concatenate([old_score, score])[first]
            order = np.lexsort((got, -score))[: self.k]
            got, score = got[order], score[order]
        self.held[query] = (got, score)

    def rows(self) -> pa.RecordBatch:
        n = [len(g) for g, _ in self.held]
        ids, score = (np.concatenate([h[c] for h in self.held]) if self.held else np.zeros(0) for c in (0, 1))
        return pa.RecordBatch.from_arrays([pa.array(np.repeat(self.ids, n), pa.int64()), pa.array(ids, pa.int64()), pa.array(score, pa.float64())], names=["asker", "rep", "score"])


_DEALT = "part long, bucket int, asks int, rep long, v array<double>, buckets binary"


def _dealt_rows(tables: int, probes: int, is_query: bool):
    """Rows with their table's first axis as part; a query once for each first axis, with all second axes that it probes there."""

    def rows(batches):
        rotations: dict[int, Rotations] = {}
        step = 32 if is_query else 256
        for batch in batches:
            for at in range(0, batch.num_rows, step):
                for ids, x in _matrices(batch.slice(at, step)):
                    dim = x.shape[1]
                    turns = rotations.setdefault(dim, Rotations(dim, tables))
                    axes, unit = 2 * turns.size, x / _norms(x)[:, None]
                    lists = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, dim), pa.int32()), pa.array(x.ravel()))
                    if is_query:
                        row, table, bucket = turns.probes(unit, probes)
                        part, second = table * axes + bucket // axes, bucket % axes
                        order = np.lexsort((second, part, row))
                        row, part, second = row[order], part[order], second[order]
                        cut = np.flatnonzero(np.r_[True, (np.diff(row) != 0) | (np.diff(part) != 0)])
                        asked = [second[a:b].astype("<i4").tobytes() for a, b in zip(cut, np.r_[cut[1:], len(row)], strict=True)]
                        row, part, bucket = row[cut], part[cut], np.full(len(cut), -1)
                    else:
                        row = np.tile(np.arange(len(x)), tables)
                        part = np.concatenate([t * axes + turns.axes(unit, 2 * t) for t in range(tables)])
                        bucket = np.concatenate([turns.axes(unit, 2 * t + 1) for t in range(tables)])
                        asked = [None] * len(row)
                    columns = [pa.array((dim << 40) + part, pa.int64()), pa.array(bucket, pa.int32()), pa.array(np.full(len(row), int(is_query)), pa.int32()), pa.array(ids[row], pa.int64()), lists.take(pa.array(row)), pa.array(asked, pa.binary())]
                    yield pa.RecordBatch.from_arrays(columns, names=[c.split()[0] for c in _DEALT.split(", ")])

    return rows


def _met_rows(k: int):
    """Rows come sorted by part, share and bucket, and the queries of a part before its rows; buckets are compared one at a time, a large one in runs."""

    def rows(batches):
        state: dict = {"part": None, "asks": [], "best": None, "who": {}}
        run: list[tuple[np.ndarray, np.ndarray]] = []

        def compare(bucket: int) -> None:
            if run and (asking := state["who"].get(bucket)):
                ids, x = (np.concatenate(c) for c in zip(*run, strict=True))
                norm = _norms(x)
                for n in asking:
                    state["best"].add(n, ids, x, norm)
            run.clear()

        def ready() -> None:
            """All queries of the part are known."""
            if state["asks"]:
                ids, q, wanted = zip(*state["asks"], strict=True)
                state["best"], state["who"] = Best(np.array(ids, np.int64), np.stack(q), k), {}
                for n, w in enumerate(wanted):
                    for b in np.frombuffer(w, "<i4").tolist():
                        state["who"].setdefault(b, []).append(n)
                state["asks"] = []

        at, held = None, 0
        for batch in batches:
            part, share, bucket, asks = (batch.column(c).to_numpy() for c in range(4))
            ids = batch.column(4).to_numpy()
            key = np.stack([part, share, bucket, asks])
            cut = np.r_[0, np.flatnonzero((np.diff(key, axis=1) != 0).any(axis=0)) + 1, len(part)] if len(part) else np.zeros(1, np.int64)
            vectors, wanted = batch.column(5), batch.column(6)
            for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
                if at is not None and (part[a], share[a], bucket[a]) != at:
                    compare(at[2])
                    held = 0
                if (part[a], share[a]) != state["part"]:
                    if state["best"] is not None:
                        yield state["best"].rows()
                    state |= {"part": (part[a], share[a]), "asks": [], "best": None, "who": {}}
                at = (part[a], share[a], bucket[a])
                x = vectors.slice(a, b - a).flatten().to_numpy().reshape(b - a, -1)
                if asks[a]:
                    state["asks"] += list(zip(ids[a:b].tolist(), x, wanted.slice(a, b - a).to_pylist(), strict=True))
                    continue
                ready()
                if bucket[a] in state["who"]:
                    run.append((ids[a:b], x))
                    held += x.size
                    if held > HELD:
                        compare(at[2])
                        held = 0
        if at is not None:
            compare(at[2])
        if state["best"] is not None:
            yield state["best"].rows()

    return rows


def _candidates(classes: DataFrame, asked: DataFrame, k: int, tables: int, probes: int) -> DataFrame:
    """(asker, rep, score): of each asked vector the k best of the rows in its buckets, best of each part still to be merged."""
    n = partitions(classes.sparkSession)
    rows = classes.select("rep", "v").mapInArrow(_dealt_rows(tables, probes, False), _DEALT)
    queries = asked.select("rep", "v").mapInArrow(_dealt_rows(tables, probes, True), _DEALT)
    # a part with many queries is dealt to shares: its queries by number, its rows to each share
    numbers = asked.agg(F.coalesce(F.sum(F.size("v")), F.lit(0))).first()[0]
    shares = max(1, -(-numbers // (8 * HELD)))
    dealt = queries.withColumn("share", F.pmod(F.xxhash64("rep"), F.lit(shares)).cast("int")).unionByName(rows.withColumn("share", F.explode(F.array(*(F.lit(s) for s in range(shares))))))
    dealt = dealt.select("part", "share", "bucket", "asks", "rep", "v", "buckets").repartition(4 * n, "part", "share").sortWithinPartitions("part", "share", "bucket")
    return dealt.mapInArrow(_met_rows(k), "asker long, rep long, score double")


def _compared(classes: DataFrame, asked: DataFrame, k: int, block: int) -> DataFrame:
    """(asker, rep, score) as above, from every row: queries go out in blocks of bounded size."""
    spark = classes.sparkSession
    blocks, parts = max(1, -(-asked.count() // block)), []
    for b in range(blocks):
        some = asked.filter(F.pmod(F.xxhash64("rep"), F.lit(blocks)) == b).select("rep", "v").toArrow().combine_chunks()
        sent = spark.sparkContext.broadcast([m for batch in some.to_batches() for m in _matrices(batch)] if some.num_rows else [])

        def found(batches, sent=sent):
            every = [Best(ids, q, k) for ids, q in sent.value]
            for batch in batches:
                for ids, x in _matrices(batch):
                    norm = _norms(x)
                    for held in every:
                        if held.q.shape[1] == x.shape[1]:
                            for n in range(len(held.ids)):
                                held.add(n, ids, x, norm)
            for held in every:
                yield held.rows()

        parts.append(classes.select("rep", "v").mapInArrow(found, "asker long, rep long, score double"))
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def _answers(found: DataFrame, classes: DataFrame, askers: DataFrame, k: int) -> DataFrame:
    """(query_id, asker, rank, vec_id, score) from the best classes of each asked vector: their rows, without the query's own number."""
    order = Window.partitionBy("asker").orderBy(F.desc("score"), "rep")
    near = found.groupBy("asker", "rep").agg(F.max("score").alias("score")).withColumn("place", F.row_number().over(order)).filter(F.col("place") <= k + 1).drop("place")
    each = near.join(classes.select("rep", "ids"), "rep").select("asker", "score", F.explode("ids").alias("vec_id"))
    # k + 1 rows are enough for any query of a class, since it leaves out one number
    order = Window.partitionBy("asker").orderBy(F.desc("score"), "vec_id")
    short = each.distinct().withColumn("place", F.row_number().over(order)).filter(F.col("place") <= k + 1)
    lists = short.groupBy("asker").agg(F.array_sort(F.collect_list(F.struct("place", "vec_id", "score"))).alias("near"))
    mine = askers.join(lists, "asker").withColumn("near", F.slice(F.filter("near", lambda s: s.vec_id != F.col("query_id")), 1, k))
    return mine.select("query_id", "asker", F.posexplode("near").alias("at", "n")).select("query_id", "asker", (F.col("at") + 1).cast("int").alias("rank"), "n.vec_id", "n.score")


def neighbours(rows: DataFrame, is_query: Column, k: int = 5, id_col: str = "vec_id", vector: str = "embedding", tables: int = TABLES, probes: int = PROBES, query_block: int = QUERIES) -> DataFrame:
    """(query_id, rank, vec_id, score): the k nearest rows of each query row by cosine, among all rows but itself.

    Every row is indexed.  Equal vectors are one class, of which the k + 1
    smallest numbers can be answers, so that copies are neither compared with
    each other nor gathered.  Queries that get fewer than k rows from their
    buckets are compared with every row, in blocks.  Rows whose id is null, or
    whose vector is null, empty, zero, or holds null or non-finite components
    take no part; vectors of other lengths than a query's are not its candidates;
    copies of a row are candidates of each other unless they share its id; a
    query row that comes several times is answered once.  An empty table gives an
    empty result; other columns are not read.
    """
    light = rows.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector).cast("array<double>").alias("v"), F.coalesce(is_query, F.lit(False)).alias("asks")).filter(F.col("vec_id").isNotNull() & usable("v"))
    # the smallest numbers of each class: Spark cuts to them in every task before the shuffle
    first = F.row_number().over(Window.partitionBy("v").orderBy("vec_id"))
    few = light.select("vec_id", "v").withColumn("n", first).filter(F.col("n") <= k + 1)
    few = few.groupBy("v").agg(F.sort_array(F.collect_set("vec_id")).alias("ids"))
    classes = stored(few.withColumn("hash", F.xxhash64("v")).withColumn("rep", F.col("ids")[0]), "classes")
    # a class goes by its smallest number, which orders ties; where a number repeats with other vectors, by its hash
    shared = often(classes, "rep", 1)
    if shared is not None:
        classes = stored(matched(classes, shared, "rep", "left").withColumn("rep", F.when(F.col("often"), F.col("hash")).otherwise(F.col("rep"))).drop("often"), "classes")
    asking = light.filter("asks").select(F.col("vec_id").alias("query_id"), F.xxhash64("v").alias("hash")).distinct()
    askers = stored(matched(asking, classes.select("hash", F.col("rep").alias("asker")), "hash").select("query_id", "asker"), "askers")
    asked = stored(matched(classes, askers.select(F.col("asker").alias("rep")).distinct(), "rep"), "asked")
    near = stored(_answers(_candidates(classes, asked, k + 1, tables, probes), classes, askers, k), "near")
    full = near.filter(F.col("rank") == k).select("query_id", "asker")
    short = stored(askers.join(full, ["query_id", "asker"], "left_anti"), "short")
    if short.isEmpty():
        return near.select("query_id", "rank", "vec_id", "score")
    open_ = stored(matched(classes, short.select(F.col("asker").alias("rep")).distinct(), "rep"), "open")
    whole = _answers(_compared(classes, open_, k + 1, query_block), classes, short, k)
    return near.join(full, ["query_id", "asker"], "left_semi").unionByName(whole).select("query_id", "rank", "vec_id", "score")
