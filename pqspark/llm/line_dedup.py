"""Line dedup by site-relative frequency, in DataFrame operations only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pqspark.llm.common import matched, stored


def host_of(url: str = "url") -> Column:
    """The host part of a URL in lower case; empty where there is none."""
    return F.coalesce(F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/@]*@)?([^/:?#]+)", 1)), F.lit(""))


def boilerplate(docs: DataFrame, host: Column, percent: int = 5, least: int = 5) -> DataFrame:
    """(host, bad): of each host the hashes of lines on more than percent of its pages, and on least pages or more.

    A page counts once for a line however often it repeats it; empty lines never
    count.  A host can have at most (mean lines of a page) * 100 / percent such
    lines, so bad is short.
    """
    pages = docs.select(host.alias("host"), F.array_distinct(F.transform(F.filter(F.split("text", "\n"), lambda x: x != ""), lambda x: F.xxhash64(x))).alias("lines"))
    counts = pages.select("host", F.explode("lines").alias("line")).groupBy("host", "line").agg(F.count("*").alias("n")).filter(F.col("n") >= least)
    totals = docs.select(host.alias("host")).groupBy("host").agg(F.count("*").alias("total"))
    frequent = counts.join(totals, "host").filter(F.col("n") * 100 > F.col("total") * percent)
    return frequent.groupBy("host").agg(F.collect_set("line").alias("bad"))


def without_boilerplate(docs: DataFrame, host: Column | None = None, percent: int = 5, least: int = 5) -> DataFrame:
    """docs with their frequent lines dropped, and (n_lines, n_dropped).

    host defaults to the source column, which is the site of a document without
    a URL; host_of(url) gives it for pages.  A null host counts as the empty one,
    and its rows are its pages.  A null text stays null with no lines, an empty
    text is one empty line.  Every row stays, also when all its lines go (the
    text is then empty); repeated rows are pages of their own; an empty table
    gives an empty one.  Columns named n_lines or n_dropped are replaced; all
    others pass through, whatever they are called.
    """
    others = [c for c in docs.columns if c not in ("n_lines", "n_dropped")]
    site = F.coalesce(host if host is not None else F.col("source"), F.lit(""))
    bad = stored(boilerplate(docs, site, percent, least), "boilerplate")
    held = matched(docs.select(F.struct(*others).alias("row"), site.alias("host"), F.split("text", "\n").alias("lines")), bad, "host", "left")
    left = F.when(F.col("bad").isNull(), F.col("lines")).otherwise(F.filter("lines", lambda x: ~F.array_contains(F.col("bad"), F.xxhash64(x))))
    held = held.withColumn("left", left)
    text = F.array_join("left", "\n")
    n = lambda c: F.when(F.col("lines").isNull(), 0).otherwise(F.size(c))
    return held.select(
        *((text if c == "text" else F.col("row").getField(c)).alias(c) for c in others),
        n("lines").alias("n_lines"),
        (n("lines") - n("left")).alias("n_dropped"),
    )


ORACLE = """
WITH d AS (SELECT doc_id, coalesce(source, '') AS host, text, string_split(text, chr(10)) AS ls FROM documents),
l AS (SELECT host, unnest(list_distinct(ls)) AS line FROM d),
c AS (SELECT host, line, count(*) AS n FROM l WHERE line <> '' GROUP BY 1, 2),
t AS (SELECT host, count(*) AS total FROM d GROUP BY 1),
b AS (SELECT host, list(line) AS bad FROM c JOIN t USING (host) WHERE n >= 5 AND n * 100 > total * 5 GROUP BY 1),
r AS (SELECT doc_id, text, ls, list_filter(ls, lambda x: NOT list_contains(coalesce(bad, []), x)) AS rest FROM d LEFT JOIN b USING (host))
SELECT doc_id, coalesce(len(ls), 0)::INT AS n_lines, coalesce(len(ls) - len(rest), 0)::INT AS n_dropped,
       CASE WHEN text IS NULL THEN NULL ELSE coalesce(array_to_string(rest, chr(10)), '') END AS text
FROM r
"""
