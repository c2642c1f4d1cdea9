"""Mixing sources to target weights by Pfair scheduling, in DataFrame operations only.

Time is cut into slots, and a slot takes one block of one source.  A source of
weight w gets a window for each of its blocks: block k is released at
floor(k / w) and due at ceil((k + 1) / w).  Taking the earliest due of the
released blocks in every slot meets all dates when the weights add up to one, and
every source is then less than one block from its share at any time.  Weights are
whole parts of a period, so one period is scheduled and repeats.  The period grows
with the number of sources, so that each has its part.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pqspark.llm.common import matched, often, stored

#: Slots of a period, at least in all and at least for each source, and rows of a block.
PERIOD, SOURCE_SLOTS, BLOCK_ROWS = 1000, 10, 16
#: Digits of the hash by which a source's rows are cut into parts, and rows of one number that may share a part.
PREFIX, REPEATS = 3, 10_000
PLACES = ("block", "row_in_block", "slot", "release", "due")


def tempered(docs: DataFrame, source: Column, period: int = PERIOD) -> DataFrame:
    """(source, parts): whole parts of the period (longer where sources are many) near to the square root of each source's rows, one at least.

    All in whole numbers: each source gets the floor of its share, and the parts
    left over go to the largest remainders (ties: by name).
    """
    sizes = docs.groupBy(source.alias("source")).agg(F.floor(F.sqrt(F.count("*").cast("double"))).cast("long").alias("root"))
    every = sizes.agg(F.sum("root").alias("roots"), F.count("*").alias("n"))
    every = every.withColumn("period", F.greatest(F.lit(period), SOURCE_SLOTS * F.col("n")))
    share = sizes.crossJoin(F.broadcast(every)).withColumn("spread", F.col("period") - F.col("n"))  # one row: the totals
    share = share.withColumn("whole", F.expr("1 + spread * root div roots")).withColumn("rest", F.expr("spread * root % roots"))
    left = F.col("period") - F.sum("whole").over(Window.partitionBy())  # a row per source
    place = F.row_number().over(Window.orderBy(F.desc("rest"), "source"))
    return share.withColumn("left", left).withColumn("parts", F.col("whole") + (place <= F.col("left")).cast("long")).select("source", "parts")


def period_plan(weights: DataFrame) -> DataFrame:
    """(source, parts, period, slots): in which slots of a period each source's blocks are taken.

    weights(source, parts) holds one row per source; parts that are null or less
    than 1 raise an error.
    The fold below carries the released blocks that wait, each as a number that
    sorts by due date and then by source; a slot adds those released in it and
    takes the smallest.
    """
    listed = weights.select("source", F.when(F.col("parts") > 0, F.col("parts")).otherwise(F.raise_error(F.lit("parts must be 1 or more"))).cast("long").alias("parts"))
    total = listed.agg(F.sum("parts").alias("period"), F.count("*").alias("n"))
    numbered = listed.withColumn("i", F.row_number().over(Window.orderBy("source", "parts")) - 1).crossJoin(F.broadcast(total))  # one row: the totals
    blocks = numbered.withColumn("k", F.explode(F.expr("sequence(0L, parts - 1L)")))
    due = F.expr("(((k + 1) * period + parts - 1) div parts) * n + i")
    released = blocks.groupBy(F.expr("(k * period) div parts").alias("t")).agg(F.collect_list(due).alias("blocks"))
    slots = total.filter("period > 0").select(F.explode(F.expr("sequence(0L, period - 1L)")).alias("t")).join(released, "t", "left")
    steps = slots.agg(F.array_sort(F.collect_list(F.struct("t", F.coalesce("blocks", F.expr("cast(array() as array<bigint>)")).alias("blocks")))).alias("steps"))
    picked = steps.withColumn(
        "picks",
        F.expr("""
            aggregate(
                steps,
                named_struct('open', cast(array() as array<bigint>), 'picks', cast(array() as array<bigint>)),
                (s, step) -> transform(
                    array(s.open || step.blocks),
                    open -> named_struct('open', array_remove(open, array_min(open)), 'picks', s.picks || array(array_min(open))))[0],
                s -> s.picks)
        """),
    )
    taken = picked.select(F.posexplode("picks").alias("t", "block")).crossJoin(F.broadcast(total)).groupBy(F.expr("block % n").alias("i")).agg(F.array_sort(F.collect_list("t")).alias("slots"))
    return numbered.join(taken, "i").select("source", "parts", "period", "slots")


def mixed(docs: DataFrame, weights: DataFrame | None = None, source: str = "source", id_col: str = "doc_id", block_rows: int = BLOCK_ROWS) -> DataFrame:
    """docs with their place in the mix: (block, row_in_block, slot, release, due).

    Within a source rows are ordered by the hash of their number (ties: number,
    then the row's hash), so blocks are shuffled alike on any cluster.  Sorting
    by (slot, row_in_block) gives the mix.  All rows are kept: once a source has
    no more blocks its slots stay empty and the others go on in proportion.  A
    null source counts as the empty one, empty and long texts are rows like any
    other, and repeated rows have places of their own.  A number that comes more
    than REPEATS times is dealt by chance to parts behind all others.  Columns of
    docs that are named like a new one are replaced.  A source without a weight
    is an error.  An empty table gives an empty result.
    """
    others = [c for c in docs.columns if c not in PLACES]
    src = F.coalesce(F.col(source).cast("string"), F.lit(""))
    held = docs.select(F.struct(*others).alias("row"), src.alias("src"), F.coalesce(F.col(id_col).cast("string"), F.lit("")).alias("number"))
    own = weights if weights is not None else tempered(docs, src)
    plan = stored(period_plan(own).withColumnRenamed("source", "src"), "plan")
    keyed = held.withColumn("key", F.md5("number")).withColumn("part", F.substring("key", 1, PREFIX))
    # a source is ranked in parts, each counted first, so that neither a source nor a number is sorted in one task
    repeats = often(held, "number", REPEATS)
    if repeats is not None:
        salt = F.lpad(F.hex(F.pmod(F.monotonically_increasing_id(), F.lit(4096))), 3, "0")
        keyed = matched(keyed, repeats, "number", "left").withColumn("part", F.when(F.col("often"), F.concat(F.lit("~"), "key", salt)).otherwise(F.col("part")))
        keyed = stored(keyed.drop("often"), "keyed")  # chance must fall once
    counts = keyed.groupBy("src", "part").agg(F.count("*").alias("n"))
    before = counts.select("src", "part", (F.sum("n").over(Window.partitionBy("src").orderBy("part")) - F.col("n")).alias("before"))
    rank = F.row_number().over(Window.partitionBy("src", "part").orderBy("key", "number", F.xxhash64("row")))
    placed = keyed.withColumn("rank", rank).join(before, ["src", "part"]).withColumn("at", F.col("before") + F.col("rank") - 1)
    placed = matched(placed, plan, "src", "left").withColumn("slots", F.coalesce("slots", F.raise_error(F.lit("a source has no weight"))))
    placed = placed.withColumn("block", F.expr(f"at div {block_rows}")).withColumn("row_in_block", (F.col("at") % block_rows).cast("int"))
    placed = placed.withColumn("k", F.expr("block % parts")).withColumn("start", F.expr("(block div parts) * period"))
    return placed.select(
        *(F.col("row").getField(c).alias(c) for c in others),
        "block",
        "row_in_block",
        F.expr("start + slots[cast(k as int)]").alias("slot"),
        F.expr("start + (k * period) div parts").alias("release"),
        F.expr("start + ((k + 1) * period + parts - 1) div parts").alias("due"),
    )


def interleaved(docs: DataFrame, weights: DataFrame | None = None, block_rows: int = BLOCK_ROWS, places: tuple[str, ...] = ()) -> DataFrame:
    """docs in the order of the mix, whatever their columns: files in sequence, and rows within them, follow (slot, row_in_block).

    places: names under which these two go along, for a later stage that reads rows in no order.
    """
    whole = docs.select(F.struct(*docs.columns).alias("whole"), F.col("doc_id"), F.col("source"))
    placed = mixed(whole, weights, block_rows=block_rows)
    return placed.repartitionByRange("slot", "row_in_block").sortWithinPartitions("slot", "row_in_block").select(*(F.col("whole").getField(c).alias(c) for c in docs.columns if c not in places), *(F.col(c).alias(to) for c, to in zip(("slot", "row_in_block"), places)))


ORACLE = f"""
WITH RECURSIVE d AS (SELECT doc_id, coalesce(source, '') AS source, md5(coalesce(doc_id::VARCHAR, '')) AS k FROM documents),
z AS (SELECT source, floor(sqrt(count(*)::DOUBLE))::BIGINT AS root FROM d GROUP BY 1),
e AS (SELECT sum(root)::BIGINT AS roots, count(*) AS n, greatest({PERIOD}, {SOURCE_SLOTS} * count(*)) AS period FROM z),
h AS (SELECT source, period, 1 + ((period - n) * root) // roots AS whole, ((period - n) * root) % roots AS rest FROM z, e),
w AS (SELECT source, whole + (row_number() OVER (ORDER BY rest DESC, source) <= period - sum(whole) OVER ())::BIGINT AS parts FROM h),
a AS (SELECT list(parts ORDER BY source) AS c, list(source ORDER BY source) AS names, any_value(period) AS period FROM w, e),
steps AS (
    SELECT -1 AS t, list_transform(c, lambda x: 0::BIGINT) AS had, NULL::BIGINT AS pick FROM a
    UNION ALL
    SELECT t, list_transform(had, lambda x, i: x + (i = pick)::BIGINT), pick FROM (
        SELECT t + 1 AS t, had, list_min(list_filter(list_transform(had, lambda x, i:
            CASE WHEN x * period < (t + 2) * c[i] THEN ((x + 1) * period + c[i] - 1) // c[i] * 100000 + i END),
            lambda y: y IS NOT NULL)) % 100000 AS pick
        FROM steps, a WHERE t < period - 1)
),
p AS (SELECT names[pick] AS source, t, row_number() OVER (PARTITION BY pick ORDER BY t) - 1 AS k FROM steps, a WHERE t >= 0),
r AS (SELECT doc_id, source, row_number() OVER (PARTITION BY source ORDER BY k, doc_id) - 1 AS pos FROM d),
b AS (SELECT doc_id, source, pos // {BLOCK_ROWS} AS block, (pos % {BLOCK_ROWS})::INT AS row_in_block, parts, period, (pos // {BLOCK_ROWS}) % parts AS k, ((pos // {BLOCK_ROWS}) // parts) * period AS start FROM r JOIN w USING (source), e)
SELECT doc_id, b.source, block, row_in_block, start + t AS slot, start + (b.k * period) // parts AS release, start + ((b.k + 1) * period + parts - 1) // parts AS due
FROM b JOIN p ON b.source = p.source AND b.k = p.k
"""
