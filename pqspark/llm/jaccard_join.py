"""N-gram Jaccard join by T-occurrence search with DivideSkip.

Equal shingle sets become one node first.  Part signatures (`Parts`) then tie
every two nodes that may be similar enough into one block, without a missed
pair.  Blocks that grow large by chance agreements are cut again by size and by
the rarest shingles of each set, again without a missed pair.  Within a block the search named above runs on inverted lists: a query with threshold T
sets its longest lists aside (at most T-1), merges the short ones, and probes
the long ones by binary search only for documents that can still reach T.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pqspark.llm.common import lean_batches, matched, partitions, release_memory, release_shuffles, stored
from pqspark.llm.graph import components
from pqspark.llm.shingles import Parts, U, fingerprint, mix, shingle_sets

#: Shingles in one inverted index; larger blocks are refined by prefixes and then split into shards of this size.
BLOCK = 500_000
#: Counters of the frequency sketch that orders shingles from rare to frequent, and how many are sent together.
COUNTERS, CHUNK = 1 << 25, 1 << 18
#: Times that large blocks are cut again at most; what is large after that is searched in shards.
ROUNDS = 6
#: Signatures that a task gathers before it ties and packs them.
HELD = 400_000
#: Checks of one signature that are compared with each other, at most.
MANY = 4096
#: Shingles, about, of the sets that common shingles are learned from; sets of those that make one common; ranges of them counted apart.
LEARNED, OFTEN, RANGES = 8_000_000, 3, 16


def _sets(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[tuple[pa.RecordBatch, Iterator[np.ndarray]]]:
    for batch in batches:
        for at in range(0, batch.num_rows, 500):
            part = batch.slice(at, 500)
            yield part, shingle_sets(part.column(part.schema.get_field_index("text")), width)


def _node_rows(width: int):
    def rows(batches):
        for batch, sets in _sets(batches, width):
            made = [(fingerprint(s), len(s)) for s in sets]
            node = pa.array([f if n else None for f, n in made], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), node, pa.array([n for _, n in made], pa.int64())], names=["doc_id", "node", "n_shingles"])

    return rows


class Forest:
    """Union-find on any hashable nodes; the smallest node is the root."""

    def __init__(self):
        self.parent: dict = {}

    def find(self, x):
        parent = self.parent
        root = x
        while (up := parent.get(root, root)) != root:
            root = up
        while x != root:
            parent[x], x = root, parent.get(x, x)
        return root

    def union(self, a, b) -> bool:
        a, b = self.find(a), self.find(b)
        if a == b:
            return False
        if b < a:
            a, b = b, a
        self.parent[b] = a
        return True

    def edges(self) -> tuple[np.ndarray, np.ndarray]:
        u = np.fromiter(self.parent, np.int64, len(self.parent))
        v = np.fromiter((self.find(x) for x in list(self.parent)), np.int64, len(self.parent))
        return u[u != v], v[u != v]


def _tie(forest: Forest, u: np.ndarray, v: np.ndarray) -> None:
    """Unite the ends of every edge, each distinct edge once."""
    order = np.lexsort((v, u))
    u, v = u[order], v[order]
    new = np.ones(len(u), bool)
    new[1:] = (u[1:] != u[:-1]) | (v[1:] != v[:-1])
    for a, b in zip(u[new].tolist(), v[new].tolist(), strict=True):
        forest.union(a, b)


def _groups(sig: np.ndarray, check: np.ndarray, node: np.ndarray) -> tuple[np.ndarray, ...]:
    """Of each signature and check the first (signature, check, node), and (node, first node) for the others that have both.

    The lowest bit (upper) does not tell signatures apart; a node with it set
    comes first.
    """
    order = np.lexsort((~sig, check))
    order = order[np.argsort(~sig[order] | U(1), kind="stable")]
    sig, check, node = sig[order], check[order], node[order]
    head = np.ones(len(sig), bool)
    head[1:] = ((sig[1:] | U(1)) != (sig[:-1] | U(1))) | (check[1:] != check[:-1])
    first = node[head][np.cumsum(head) - 1]
    tied = ~head & (first != node)
    return sig[head], check[head], node[head], node[tied], first[tied]


def _alike(sig: np.ndarray, check: np.ndarray, node: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of nodes with the same signature, upper in one of them, whose checks are as near as similar sets' are.

    Nodes with the same check are tied to one of them, which is compared for
    all.  A signature that more than MANY checks go with ties all its nodes.
    """
    order = np.argsort(~sig, kind="stable")
    head = np.ones(len(sig), bool)
    head[1:] = (sig[order][1:] | U(1)) != (sig[order][:-1] | U(1))
    size = np.diff(np.r_[np.flatnonzero(head), len(sig)])
    useful = (size > 1) & (sig[order][head] & U(1)).astype(bool)
    order = order[np.repeat(useful, size)]  # few are left
    sig, check, node, u, v = _groups(sig[order], check[order], node[order])
    us, vs = [u], [v]
    start = np.flatnonzero(np.r_[True, (sig[1:] | U(1)) != (sig[:-1] | U(1))]) if len(sig) else np.zeros(0, np.int64)
    size = np.diff(np.r_[start, len(sig)])
    first, end = np.repeat(start, size), np.repeat(start + size, size)
    many = end - first > MANY
    us.append(node[many])
    vs.append(node[first[many]])
    at, off, limit = np.flatnonzero(~many), 1, Parts.limit(sig)
    while len(at := at[at + off < end[at]]):
        near = np.bitwise_count(check[at] ^ check[at + off]) <= limit[at]
        near &= ((sig[at] | sig[at + off]) & U(1)).astype(bool)
        us.append(node[at[near]])
        vs.append(node[at[near] + off])
        off += 1
    return np.concatenate(us), np.concatenate(vs)


def _counter(shingles: np.ndarray, block: int) -> np.ndarray:
    return (mix(shingles ^ U(block & (1 << 64) - 1)) % U(COUNTERS)).astype(np.int64)


def _sketch_rows(width: int):
    """(chunk, part, counts): how many sets of a partition have a shingle of each counter, packed; part deals them out for a first sum."""

    def rows(batches):
        part = TaskContext.get().partitionId() % 32
        counts = np.zeros(COUNTERS, np.uint8)
        for batch, sets in _sets(batches, width):
            for s, block in zip(sets, batch.column(batch.schema.get_field_index("block")).to_pylist(), strict=True):
                at = np.unique(_counter(s, block))
                counts[at] += counts[at] < 255
        press = zstandard.ZstdCompressor(level=1)
        used = [k for k in range(COUNTERS // CHUNK) if counts[k * CHUNK : (k + 1) * CHUNK].any()]
        for k in used:
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([part], pa.int32()), pa.array([press.compress(counts[k * CHUNK : (k + 1) * CHUNK].tobytes())], pa.binary())], names=["chunk", "part", "counts"])

    return rows


def _sketch_sums(table: pa.Table) -> pa.Table:
    total = np.zeros(CHUNK, np.int64)
    for one in table.column("counts"):
        total += np.frombuffer(zstandard.ZstdDecompressor().decompress(one.as_py()), np.uint8)
    packed = zstandard.ZstdCompressor(level=1).compress(np.minimum(total, 255).astype(np.uint8).tobytes())
    return pa.table({"chunk": table.column("chunk")[:1], "counts": pa.array([packed], pa.binary())})


def sketch(docs: DataFrame, width: int) -> np.ndarray:
    """How many of docs(text, block) hold a shingle of each counter (255: that or more): never too few, of fixed size whatever the corpus holds."""
    parts = docs.mapInArrow(_sketch_rows(width), "chunk int, part int, counts binary")
    for by in (("chunk", "part"), ("chunk",)):
        parts = parts.groupBy(*by).applyInArrow(_sketch_sums, "chunk int, counts binary")
    out = np.zeros(COUNTERS, np.uint8)
    for row in parts.collect():
        out[row.chunk * CHUNK : (row.chunk + 1) * CHUNK] = np.frombuffer(zstandard.ZstdDecompressor().decompress(row.counts), np.uint8)
    return out


def prefix(shingles: np.ndarray, counts: np.ndarray, num: int, den: int) -> np.ndarray:
    """The rarest shingles, of which two sets with Jaccard num/den or more share one; those in one set only are left out.

    The order, by count and then by hash, is the same for all sets.  Two such
    sets share at least num/den of each, so that each one's first
    n - ceil(n * num / den) + 1 shingles meet.
    """
    order = np.lexsort((shingles, counts))[: len(shingles) + (-num * len(shingles) // den) + 1]
    return shingles[order][counts[order] > 1]


def _common_rows(width: int):
    """(range, shingles, counts): how many of a partition's sets have each shingle, packed by range of hashes."""

    def rows(batches):
        held, seen = [np.zeros(0, np.uint64)], set()
        for batch, sets in _sets(batches, width):
            for s, node in zip(sets, batch.column(batch.schema.get_field_index("node")).to_pylist(), strict=True):
                if node not in seen:
                    seen.add(node)
                    held.append(s)
        found, counts = np.unique(np.concatenate(held), return_counts=True)
        bound = np.searchsorted(found, np.array([(k << 64) // RANGES for k in range(1, RANGES)], np.uint64))
        packed = [[x.tobytes() for x in np.split(column, bound)] for column in (found, counts.astype(np.int32))]
        yield pa.RecordBatch.from_arrays([pa.array(range(RANGES), pa.int32()), *(pa.array(c, pa.binary()) for c in packed)], names=["range", "shingles", "counts"])

    return rows


def _common_sums(table: pa.Table) -> pa.Table:
    found, at = np.unique(np.concatenate([np.frombuffer(x.as_py(), np.uint64) for x in table.column("shingles")]), return_inverse=True)
    counts = np.bincount(at, np.concatenate([np.frombuffer(x.as_py(), np.int32) for x in table.column("counts")]), len(found))
    return pa.table({"shingles": pa.array([found[counts >= OFTEN].tobytes()], pa.binary())})


def common_shingles(texts: DataFrame, first: DataFrame, width: int) -> np.ndarray:
    """The shingles, sorted, that OFTEN or more of some sets have; these are chosen by hash and hold about LEARNED shingles.

    They only order the parts that a set signs, so that it signs what few others
    have; which of them are found decides on no pair.
    """
    total = first.agg(F.sum("size")).first()[0] or 0
    share = min(1 << 20, (LEARNED << 20) // max(1, total) + 1)
    some = stored(first.filter(F.pmod(F.xxhash64("node"), F.lit(1 << 20)) < share).select("doc_id", "node"), "some")
    parts = matched(texts, some, "doc_id").select("text", "node").mapInArrow(_common_rows(width), "range int, shingles binary, counts binary")
    rows = parts.groupBy("range").applyInArrow(_common_sums, "shingles binary").collect()
    return np.sort(np.concatenate([np.zeros(0, np.uint64), *(np.frombuffer(r.shingles, np.uint64) for r in rows)]))


def _signature_rows(width: int, num: int, den: int, buckets: int, counts=None, common=None):
    """Rows (bucket, sigs, checks, nodes, u, v) with packed arrays.

    Nodes of a run of batches with the same signature and check are tied here, and one of them goes
    on: both reach their bucket at most once per run however many
    documents carry them.
    """

    def packed(sigs: list[np.ndarray], checks: list[np.ndarray], nodes: list[np.ndarray]):
        sig, check, node, u, v = _groups(np.concatenate(sigs), np.concatenate(checks), np.concatenate(nodes))
        forest = Forest()
        _tie(forest, u, v)
        u, v = forest.edges()
        at = (sig >> U(40)).astype(np.int64) % buckets
        order = np.argsort(at, kind="stable")
        at, sig, check, node = at[order], sig[order], check[order], node[order]
        cut = np.flatnonzero(np.diff(at)) + 1
        lo, hi = np.r_[0, cut].tolist(), np.r_[cut, len(at)].tolist()
        to = at[lo].tolist()
        columns = [[x[a:b].tobytes() for a, b in zip(lo, hi, strict=True)] for x in (sig, check, node)]
        columns += [[x.tobytes(), *[b""] * (len(to) - 1)] for x in (u, v)]
        return pa.RecordBatch.from_arrays([pa.array(to, pa.int32()), *(pa.array(c, pa.binary()) for c in columns)], names=["bucket", "sigs", "checks", "nodes", "u", "v"])

    def rows(batches):
        parts = Parts(num, den, None if common is None else common.value)
        sigs, checks, nodes, seen, held = [], [], [], set(), 0
        for batch, sets in _sets(batches, width):
            if counts is not None:
                node, member, block, upper = (batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("node", "member", "block", "upper"))
            for k, s in enumerate(sets):
                if not len(s):
                    continue
                f = fingerprint(s)
                if counts is not None:
                    if f != node[k]:  # another text of a doc_id that repeats
                        continue
                    f = member[k]
                if f in seen:
                    continue
                if counts is None:
                    own, check = parts.checked(s)
                else:
                    own = mix(prefix(s, counts.value[_counter(s, block[k])], num, den) ^ U(block[k] & (1 << 64) - 1))
                    own = own | U(1) if upper[k] else own & ~U(1)
                    check = np.zeros_like(own)  # one shingle that both have says all
                if not len(own):
                    continue
                seen.add(f)
                sigs.append(own)
                checks.append(check)
                nodes.append(np.full(len(own), f, np.int64))
                held += len(own)
                if held > HELD:
                    yield packed(sigs, checks, nodes)
                    sigs, checks, nodes, held = [], [], [], 0
                    seen.clear()
        if sigs:
            yield packed(sigs, checks, nodes)
        release_memory()

    return rows


def _tied_rows(batches):
    """(u, v) of a partition's buckets; rows come sorted by bucket, and one bucket is held at a time."""
    forest = Forest()
    held: list[list[bytes]] = [[], [], []]
    at = None

    def close():
        if held[0]:
            u, v = _alike(*(np.frombuffer(b"".join(x), kind) for x, kind in zip(held, (np.uint64, np.uint64, np.int64), strict=True)))
            _tie(forest, u, v)
        for x in held:
            x.clear()

    def flush():
        u, v = forest.edges()
        forest.parent.clear()
        return pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], names=["u", "v"])

    for batch in batches:
        for bucket, sigs, checks, nodes, u, v in zip(*(batch.column(k).to_pylist() for k in range(6)), strict=True):
            if bucket != at:
                close()
                at = bucket
                if len(forest.parent) > 200_000:
                    yield flush()
            for x, more in zip(held, (sigs, checks, nodes), strict=True):
                x.append(more)
            _tie(forest, np.frombuffer(u, np.int64), np.frombuffer(v, np.int64))
    close()
    yield flush()
    release_memory()


def _blocks(docs: DataFrame, width: int, num: int, den: int, counts=None, common=None) -> DataFrame:
    """(node, root): nodes that some other node may be similar to, by candidate block.

    Without counts nodes are tied by signatures of their parts (common: a broadcast list of shingles that make them weak), with counts (a broadcast
    sketch, and docs with node, block and the member's name in it) the members of each
    block are tied by rare prefixes.
    """
    spark = docs.sparkSession
    n = partitions(spark)
    rows = docs.mapInArrow(_signature_rows(width, num, den, 4 * n, counts, common), "bucket int, sigs binary, checks binary, nodes binary, u binary, v binary")
    tied = rows.repartition(n, "bucket").sortWithinPartitions("bucket").mapInArrow(_tied_rows, "u long, v long")
    edges = stored(tied.distinct(), "tied")
    del rows, tied
    release_shuffles(spark)
    return components(edges)


def _cut_again(texts: DataFrame, first: DataFrame, blocks: DataFrame, large: DataFrame, width: int, num: int, den: int, by_size: bool) -> DataFrame:
    """blocks(member, node, upper, block) with the large ones in smaller pieces that keep every pair together.

    by_size: a node becomes two members, one in the block of its own size level
    (upper) and one in that of the next level, so that similar sets, which
    differ by one level at most, still meet.  Nodes of equal level meet where
    both are upper, so pieces without an upper member are left out.
    """
    held = blocks.join(large, "block", "left_semi").join(first, "node")
    if by_size:
        level = F.floor(F.log("size") * ((1 - 1e-9) / math.log(den / num)))
        held = held.withColumn("upper", F.explode(F.array(F.lit(True), F.lit(False)))).withColumn("level", F.when(F.col("upper"), level).otherwise(level + 1))
        held = held.withColumn("member", F.xxhash64("node", "level")).withColumn("block", F.xxhash64("block", "level"))
    held = stored(held.select("doc_id", "member", "node", "upper", "block"), "held")
    again = matched(texts, held, "doc_id").select("text", "node", "member", "block", "upper")
    counts = texts.sparkSession.sparkContext.broadcast(sketch(again, width))
    finer = _blocks(again, width, num, den, counts).select(F.col("node").alias("member"), F.col("root").alias("piece"))
    finer = held.select("member", "node", "upper").join(finer, "member").withColumnRenamed("piece", "block")
    useful = finer.groupBy("block").agg(F.max("upper").alias("useful")).filter("useful").select("block")
    rest = blocks.join(large, "block", "left_anti").select("member", "node", "upper", "block")
    return rest.unionByName(finer.join(useful, "block", "left_semi").select(rest.columns))


def divide_skip(lists: list[np.ndarray], threshold: int) -> tuple[np.ndarray, np.ndarray]:
    """Documents that occur in at least threshold of the sorted lists, with their counts.

    The longest lists, at most threshold-1 of them, are set aside.  The short
    ones are merged; a document found c times there can at best reach c plus the
    number of long lists, which are then probed.
    """
    lists = sorted(lists, key=len)
    n_short = max(len(lists) - (threshold - 1), 1)
    found, count = merged(lists[:n_short])
    return probed(lists[n_short:], found, count, np.full(len(found), threshold))


def probed(long: list[np.ndarray], found: np.ndarray, count: np.ndarray, goal: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Those of found that reach their goal once the long lists are counted too.

    Each list is searched by bisection, shortest first, and only for documents
    that can still reach their goal with the lists that are left.
    """
    for done, one in enumerate(long):
        able = count + (len(long) - done) >= goal
        if not able.all():
            found, count, goal = found[able], count[able], goal[able]
        if not len(found):
            break
        at = np.searchsorted(one, found)
        at[at == len(one)] = 0
        count = count + (one[at] == found)
    reach = count >= goal
    return found[reach], count[reach]


def merged(lists: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Documents of sorted lists with the number of lists that hold each; few entries go by a heap, many by one sort."""
    total = sum(map(len, lists))
    if total == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    if total <= 64:
        ids, counts = [], []
        for x in heapq.merge(*(one.tolist() for one in lists)):
            if ids and ids[-1] == x:
                counts[-1] += 1
            else:
                ids.append(x)
                counts.append(1)
        return np.array(ids, np.int64), np.array(counts, np.int64)
    return np.unique(np.concatenate(lists), return_counts=True)


def linked(sets: list[np.ndarray], query: np.ndarray, node: np.ndarray, num: int, den: int, forest: Forest, indexed: np.ndarray | None = None) -> None:
    """Unite the nodes of every two sets of which one is a query, the other is indexed, and Jaccard is num/den or more.

    node[k] is set k's name in the forest.  Pairs that are united already need
    no count, so a tight group of copies costs one count each.
    """
    sizes = np.fromiter(map(len, sets), np.int64, len(sets))
    keys = np.concatenate(sets)
    owner = np.repeat(np.arange(len(sets)), sizes)
    if indexed is not None:
        keys, owner = keys[indexed[owner]], owner[indexed[owner]]
    order = np.argsort(keys, kind="stable")  # stable: each list is sorted by document
    keys, owner = keys[order], owner[order]
    if not len(keys):
        return
    terms, first = np.unique(keys, return_index=True)
    bound = np.r_[first, len(keys)]
    length = np.diff(bound)
    for k in np.flatnonzero(query).tolist():
        at = np.minimum(np.searchsorted(terms, sets[k]), len(terms) - 1)
        at = at[terms[at] == sets[k]]
        need = -(-num * sizes[k] // den)  # a partner at least shares num/den of the larger set
        if len(at) < need:
            continue
        at = at[np.argsort(length[at], kind="stable")]
        n_short = len(at) - (need - 1)
        found, count = merged([owner[bound[t] : bound[t + 1]] for t in at[:n_short].tolist()])
        # a self join meets each pair from its larger side (ties: later one), whose threshold is the sharper
        keep = found != k
        if indexed is None:
            keep &= (sizes[found] < sizes[k]) | ((sizes[found] == sizes[k]) & (found < k))
        keep &= (den * sizes[found] >= num * sizes[k]) & (den * sizes[k] >= num * sizes[found])
        found, count = found[keep], count[keep]
        if not len(found):
            continue
        root = forest.find(int(node[k]))
        apart = np.fromiter((forest.find(int(node[x])) != root for x in found.tolist()), bool, len(found))
        found, count = found[apart], count[apart]
        if not len(found):
            continue
        goal = -(-num * (sizes[k] + sizes[found]) // (num + den))
        for x in probed([owner[bound[t] : bound[t + 1]] for t in at[n_short:].tolist()], found, count, goal)[0].tolist():
            forest.union(int(node[k]), int(node[x]))


def _link_rows(width: int, num: int, den: int, block: int):
    """(u, v) of linked nodes; rows (doc_id, text, node, shard, role) come sorted by shard."""

    def rows(batches):
        forest = Forest()
        held: list[tuple[np.ndarray, int, int]] = []
        at, size = None, 0

        def close():
            nonlocal size
            size = 0
            if len(held) > 1:
                role = np.array([r for _, _, r in held])
                linked([s for s, _, _ in held], role < 2, np.array([n for _, n, _ in held], np.int64), num, den, forest, None if (role == 0).all() else role > 0)
                release_memory()
            held.clear()

        for batch, sets in _sets(batches, width):
            node, shard, role = (batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("node", "shard", "role"))
            for k, s in enumerate(sets):
                if fingerprint(s) != node[k]:  # another text of a doc_id that repeats
                    continue
                # whole blocks (role 0) may share an index; a part of a split block has one to itself
                if shard[k] != at and (size >= block or role[k] or (held and held[-1][2])):
                    close()
                at = shard[k]
                held.append((s, node[k], role[k]))
                size += len(s)
        close()
        u, v = forest.edges()
        yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], names=["u", "v"])

    return rows


def jaccard_components(docs: DataFrame, width: int = 5, num: int = 4, den: int = 5, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK) -> DataFrame:
    """One row per document: (doc_id, n_shingles, component_id).

    Documents link when their sets of distinct word shingles have a Jaccard
    index of at least num/den; component_id is the smallest doc_id that links
    lead to.  Null and empty texts have no shingles and link with nothing, nor
    with each other.  Rows that repeat a doc_id are documents of their own under
    the same number.  Rows with a null doc_id are returned unlinked, with a null
    component.  Other columns of docs are not read.
    """
    spark = docs.sparkSession
    lean_batches(spark)
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    nodes = stored(texts.mapInArrow(_node_rows(width), "doc_id long, node long, n_shingles long"), "nodes")
    first = nodes.filter("node is not null and doc_id is not null").groupBy("node").agg(F.min("doc_id").alias("doc_id"), F.max("n_shingles").alias("size"))

    common = spark.sparkContext.broadcast(common_shingles(texts, first, width))
    tied = _blocks(texts.filter("doc_id is not null"), width, num, den, common=common)
    blocks = stored(tied.select(F.col("node").alias("member"), "node", F.lit(True).alias("upper"), F.col("root").alias("block")), "blocks")
    before = None
    for _ in range(ROUNDS):
        large = stored(blocks.join(first, "node").groupBy("block").agg(F.sum("size").alias("size")).filter(F.col("size") > block), "large")
        now = large.agg(F.sum("size")).first()[0]
        if not now or (before and now > 0.8 * before):
            break
        blocks = stored(_cut_again(texts, first, blocks, large.select("block"), width, num, den, before is None), "blocks")
        before = now

    total = blocks.join(first, "node").groupBy("block").agg(F.ceil(F.sum("size") / F.lit(block)).cast("int").alias("shards"))
    sized = blocks.join(total, "block")
    own = F.pmod(F.xxhash64("node"), F.col("shards")).cast("int")
    # a split block: each node is indexed in its own shard (2: indexed, 1: both) and asks those after it
    placed = sized.withColumn("own", own).withColumn("to", F.explode(F.expr("sequence(own, shards - 1)")))
    placed = placed.select(
        "node",
        F.xxhash64("block", "to").alias("shard"),
        F.when(F.col("shards") == 1, 0).when(F.col("to") == F.col("own"), 1).otherwise(-1).alias("role"),
    )
    asked = matched(texts, stored(placed.join(first.drop("size"), "node"), "placed"), "doc_id").select("text", "node", "shard", "role")
    links = asked.repartition(partitions(spark), "shard").sortWithinPartitions("shard").mapInArrow(_link_rows(width, num, den, block), "u long, v long")
    edges = stored(links, "links")
    del asked, links
    release_shuffles(spark)
    roots = components(edges)
    named = nodes.join(roots, "node", "left").withColumn("class", F.coalesce("root", "node"))
    least = named.filter("class is not null").groupBy("class").agg(F.min("doc_id").alias("least"))
    return named.join(least, "class", "left").select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("least", "doc_id")).alias("component_id"))


def one_of_each(docs: DataFrame, width: int = 5, num: int = 4, den: int = 5) -> DataFrame:
    """docs with one row of each group of linked documents: that with the smallest doc_id.

    Of rows that repeat a doc_id and its text one stays.  Rows with a null doc_id
    or without words stay.
    """
    found = jaccard_components(docs, width, num, den)
    out = stored(found.filter("doc_id <> component_id").select("doc_id").distinct(), "dropped")
    twice = stored(found.filter("doc_id is not null").groupBy("doc_id").count().filter("count > 1").select("doc_id"), "twice")
    kept = matched(docs, out, "doc_id", "left_anti")
    if twice.limit(1).count():
        kept = matched(kept, twice, "doc_id", "left_anti").unionByName(matched(kept, twice, "doc_id", "left_semi").dropDuplicates(["doc_id", "text"]))
    return kept.select(docs.columns)
