"""Conflict-constrained best-fit packing of documents into sequences of fixed length.

Bins are ordered by what is left in them, and each carries a bitmap of the
sources and one of the duplicate clusters that it holds.  A piece goes to the
tightest bin that is large enough and shares neither with it: the search starts
at the piece's own length and goes on to the next larger residual until a
compatible bin is found, or opens a new bin.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pqspark.llm.common import matched, often, stored

#: Tokens of a bin, and documents that are packed together (a task never packs more at once).
CAPACITY, SHARD_ROWS = 2048, 4096


class Bins:
    """Open bins by residual; within a residual, by source bitmap, since those agree on most pieces."""

    def __init__(self, capacity: int):
        self.capacity = capacity
        self.open: dict[int, dict[int, list[int]]] = {}
        self.present = 0  # bit r: some bin has r left
        self.sources: list[int] = []
        self.clusters: list[int] = []
        self.left: list[int] = []

    def _put(self, bin_: int) -> None:
        r = self.left[bin_]
        if r:
            self.open.setdefault(r, {}).setdefault(self.sources[bin_], []).append(bin_)
            self.present |= 1 << r

    def _take(self, r: int, bitmap: int, k: int) -> int:
        group = self.open[r][bitmap]
        bin_ = group.pop(k)
        if not group:
            del self.open[r][bitmap]
            if not self.open[r]:
                del self.open[r]
                self.present &= ~(1 << r)
        return bin_

    def _tightest(self, length: int, source: int, cluster: int) -> int | None:
        above = self.present >> length
        r = length
        while above:
            step = (above & -above).bit_length() - 1
            r, above = r + step, above >> step
            for bitmap, group in self.open[r].items():
                if bitmap & source:
                    continue
                for k, bin_ in enumerate(group):
                    if not self.clusters[bin_] & cluster:
                        return self._take(r, bitmap, k)
            r, above = r + 1, above >> 1
        return None

    def place(self, length: int, source: int, cluster: int) -> tuple[int, int]:
        """(bin, offset) of a piece; source and cluster are its bits, 0 where it has none."""
        bin_ = self._tightest(length, source, cluster)
        if bin_ is None:
            bin_ = len(self.left)
            self.left.append(self.capacity)
            self.sources.append(0)
            self.clusters.append(0)
        offset = self.capacity - self.left[bin_]
        self.left[bin_] -= length
        self.sources[bin_] |= source
        self.clusters[bin_] |= cluster
        self._put(bin_)
        return bin_, offset


def pack(pieces: list[tuple], capacity: int) -> list[tuple[int, int]]:
    """(bin, offset) of each of pieces(length, source, cluster, order...), which are taken longest first."""
    bins, source_bit, cluster_bit = Bins(capacity), {}, {}
    seen: dict = {}
    for _, _, cluster, *_ in pieces:
        seen[cluster] = seen.get(cluster, 0) + 1
    out: list = [None] * len(pieces)
    for k in sorted(range(len(pieces)), key=lambda k: (-pieces[k][0], *pieces[k][3:])):
        length, source, cluster = pieces[k][:3]
        s = 0 if source is None else 1 << source_bit.setdefault(source, len(source_bit))
        c = 0 if cluster is None or seen[cluster] == 1 else 1 << cluster_bit.setdefault(cluster, len(cluster_bit))
        out[k] = bins.place(length, s, c)
    return out


SCHEMA = "doc_id long, piece int, start long, length int, shard int, bin int, bin_offset int"


def _in_runs(light: DataFrame, order: tuple[str, ...], shard_rows: int) -> DataFrame:
    """light with a shard: runs of the first column of order, a long, of shard_rows rows or so; only the counts of its ranges are put in sequence."""
    span = max(1, shard_rows // 16)
    ranged = light.withColumns({c: F.coalesce(c, F.lit(0)) for c in order}).withColumn("range", F.floor(F.col(order[0]) / span))
    counts = ranged.groupBy("range").agg(F.count("*").alias("n"))
    before = F.sum("n").over(Window.orderBy("range")) - F.col("n")  # a row for each range
    runs = stored(counts.select("range", F.floor(before / shard_rows).cast("int").alias("shard")), "runs")
    return matched(ranged, runs, "range").drop("range")


def _shard_rows(capacity: int, most: int, order: tuple[str, ...] = ()):
    def rows(table: pa.Table) -> pa.Table:
        docs = sorted(zip(*(table.column(c).to_pylist() for c in ("doc_id", "source", "cluster", "tokens", "shard", *order)), strict=True), key=lambda r: (*r[5:], r[0] is None, r[0] or 0, str(r[1]), r[2] or 0, r[3]))
        out: list[tuple] = []
        first = 0
        for at in range(0, len(docs), most):
            pieces = []
            for n, (doc_id, source, cluster, tokens, shard, *_) in enumerate(docs[at : at + most]):
                for piece, start in enumerate(range(0, tokens, capacity)):
                    pieces.append((min(capacity, tokens - start), source, cluster, n, piece, doc_id, start, shard))
            got = pack(pieces, capacity)
            out += [(p[5], p[4], p[6], p[0], p[7], first + b, o) for p, (b, o) in zip(pieces, got, strict=True)]
            first += 1 + max((b for b, _ in got), default=-1)
        names = [c.split()[0] for c in SCHEMA.split(", ")]
        kinds = {"long": pa.int64(), "int": pa.int32()}
        return pa.table({name: pa.array([r[k] for r in out], kinds[SCHEMA.split(", ")[k].split()[1]]) for k, name in enumerate(names)})

    return rows


def word_tokens(text: str = "text") -> Column:
    """Words of a text and one end mark."""
    return F.regexp_count(F.coalesce(F.col(text), F.lit("")), F.lit(r"\S+")).cast("long") + 1


def packed(docs: DataFrame, tokens: Column | None = None, cluster: Column | None = None, capacity: int = CAPACITY, shard_rows: int = SHARD_ROWS, order: tuple[str, ...] = ()) -> DataFrame:
    """One row per piece of a document: (doc_id, piece, start, length, shard, bin, bin_offset).

    A document longer than a bin is cut into full bins and a rest.  No bin holds
    two pieces of one source or of one duplicate cluster (by default: equal
    texts).  Documents are dealt to shards by hash, so that bins of a shard are
    packed by one task from a bounded number of rows; each document, empty and
    null ones too (one end mark), is in the result once.  Null sources and empty
    texts conflict with nothing.  Rows that repeat a document are documents of
    their own, which conflict by cluster; where one comes more often than a shard
    has rows, its rows are dealt by chance.  Other columns are not read; an empty
    table gives an empty result.

    With order, names of columns of whole numbers, shards are runs of that order
    in place of hashes, shard after shard, and pieces of equal length are placed
    in it.  The first is a slot, of which sixteen rows or so share a number.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    tokens = tokens if tokens is not None else word_tokens()
    cluster = cluster if cluster is not None else F.when(text != "", F.xxhash64(text))
    light = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "source", cluster.alias("cluster"), F.greatest(tokens, F.lit(1)).cast("long").alias("tokens"), *order)
    if order:
        return _in_runs(light, order, shard_rows).groupBy("shard").applyInArrow(_shard_rows(capacity, 2 * shard_rows, order), SCHEMA)
    shards = max(1, -(-docs.count() // shard_rows))
    light = light.withColumn("key", F.xxhash64("doc_id", "source", "cluster"))
    repeats = often(light, "key", shard_rows)
    if repeats is not None:
        light = matched(light, repeats, "key", "left").withColumn("key", F.when(F.col("often"), F.xxhash64("key", F.monotonically_increasing_id())).otherwise(F.col("key")))
        light = stored(light.drop("often"), "dealt")  # chance must fall once
    light = light.withColumn("shard", F.pmod("key", F.lit(shards)).cast("int")).drop("key")
    return light.groupBy("shard").applyInArrow(_shard_rows(capacity, 2 * shard_rows), SCHEMA)
