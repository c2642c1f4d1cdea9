"""Connected components of an edge table, with no hub ever gathered in one task."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pqspark.llm.common import BROADCAST_ROWS, fresh_path, matched, remove, small, stored

#: Neighbours above which a node's edges (16 bytes each) are not brought into one task.
HUB = 100_000
#: Files that HUB edges at most are stored in.
FEW_FILES = 4


def _starred(edges: DataFrame, below: bool) -> DataFrame:
    """One contraction: every neighbour of a node is tied to the node's smallest neighbour instead.

    below: only neighbours smaller than the node are moved (and the node with
    them); otherwise only larger ones.  Smallest neighbours are found by partial
    minima.  Those of hubs, which are edges / HUB at most, are sent to where the
    hubs' edges lie, so that only the edges of other nodes are dealt by node.
    """
    both = edges if below else edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).withColumn("m", F.least("m", "u"))
    moving = both if below else both.filter("v > u")
    told = moving.join(least, "u")
    many = stored(least.filter(F.col("n") > HUB).select("u", "m"), "hubs")
    if not many.isEmpty():
        rest = moving.join(F.broadcast(many) if small(many, BROADCAST_ROWS) else many, "u", "left_anti")
        told = rest.join(least, "u").select("u", "v", "m").unionByName(matched(moving, many, "u").select("u", "v", "m"))
    moved = told.select(F.col("v").alias("a"), F.col("m").alias("b"))
    if below:
        moved = moved.unionByName(least.select(F.col("u").alias("a"), F.col("m").alias("b")))
    return moved.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()


def _starred_few(edges: DataFrame, below: bool) -> DataFrame:
    """What _starred gives, for HUB edges at most: a node's edges then fit in a task, and dealing them by node once serves the minimum, the move and the next contraction."""
    both = edges if below else edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    told = both.withColumn("m", F.least(F.min("v").over(Window.partitionBy("u")), "u"))
    if below:
        moved = told.select(F.explode(F.array(F.struct(F.col("v").alias("a"), F.col("m").alias("b")), F.struct(F.col("u").alias("a"), F.col("m").alias("b")))).alias("e")).select("e.*")
    else:
        moved = told.filter("v > u").select(F.col("v").alias("a"), F.col("m").alias("b"))
    return moved.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).repartition("u").distinct()


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(u, v) of type long to (node, root): root is the smallest node that u's component holds.

    Alternates the two contractions until the edge set no longer changes, which
    takes O(log**2) rounds; each round is stored, so a lost executor repeats at
    most one, and the round before is deleted.  Self loops and repeated or null
    ends are ignored.  Nodes without an edge are not returned.  Edges that still
    change after so many rounds are an error.
    """
    spark = edges.sparkSession
    old = fresh_path(spark, "components")
    edges = stored(edges.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "components", old)
    state = lambda df: df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    before = state(edges)
    for _ in range(rounds):
        path = fresh_path(spark, "components")
        if before[0] > HUB:
            made = _starred(stored(_starred(edges, False), "components"), True)
        else:
            made = _starred_few(_starred_few(edges, False), True).coalesce(FEW_FILES)
        edges = stored(made, "components", path)
        now = state(edges)
        remove(spark, old)
        old = path
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    roots = edges.select("v").distinct()
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(roots.select(F.col("v").alias("node"), F.col("v").alias("root")))
