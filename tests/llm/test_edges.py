"""Odd rows, empty tables and clashing column names for every operator and every stage; hostile pages; whole-line windows."""

import re
import time
from collections import Counter

import pytest
from pyspark.sql import functions as F

from pqspark.llm import ann, graph, html_extract, jaccard_join, line_dedup, lm_scoring, media, packing, pfair, token_tables, toxicity

SF = "/root/testdata/sf0.001"
LONG = "word " * 200_000
ROWS = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, "same words here again", "en", "a", 4), (3, "same words here again", "en", "a", 4), (None, "one two three four five", "en", None, 5), (4, LONG, "en", "hot", 1), (5, LONG, "en", "hot", 1)]
# names that operators use for their own columns
CLASH = ("bad", "host", "parts", "block", "slot", "plan", "key", "part", "rank", "row", "often", "n_lines", "left", "lines", "shard", "cluster", "tokens", "target", "score", "component_id", "node", "like", "whole")


@pytest.fixture(scope="module")
def odd(spark):
    df = spark.createDataFrame(ROWS, "doc_id long, text string, lang string, source string, n_chars long")
    return df.select("*", *(F.lit(7).alias(c) for c in CLASH))


def per_document(docs):
    """Each operator's rows: as many as documents."""
    labels = docs.limit(0).selectExpr("doc_id", "1 AS toxic")
    yield "lm", lm_scoring.scored(docs, docs.filter("doc_id = 3").select("doc_id"))
    yield "tables", token_tables.encoded(docs)
    yield "toxicity", toxicity.scored(docs, toxicity.fit(docs, labels))
    yield "media", media.digested(docs)
    yield "lines", line_dedup.without_boilerplate(docs)
    yield "join", jaccard_join.jaccard_components(docs, 4, 85, 100)
    yield "mix", pfair.mixed(docs)


def test_operators_on_odd_rows_with_clashing_columns(odd):
    for name, made in per_document(odd):
        assert made.count() == len(ROWS) and len(set(made.columns)) == len(made.columns), name
    assert {r.doc_id for r in packing.packed(odd).collect()} == {None, 1, 2, 3, 4, 5}


def test_operators_on_empty_tables(odd):
    for name, made in per_document(odd.limit(0)):
        assert made.count() == 0, name
    assert packing.packed(odd.limit(0)).count() == 0


def test_stages_on_odd_and_empty_tables(spark, odd):
    pipeline = pytest.importorskip("corpus_pipeline")
    for docs, n in ((odd, len(ROWS)), (odd.limit(0), 0)):
        for name, stage in pipeline.STAGES[:-1]:
            made = stage(spark, docs, SF)
            assert made.columns == odd.columns, name
            assert made.count() == (n if name != "near_duplicates" else min(n, 5)), name  # 3 and 3, 4 and 5 are copies
        assert pipeline.STAGES[-1][1](spark, docs, SF).select("doc_id").distinct().count() == (6 if n else 0)


def test_pages_and_vectors_on_odd_rows(spark):
    pages = spark.createDataFrame([(1, "u", None), (None, None, ""), (2, "u", "<article><p>A text, which is long enough to be one.</p></article>"), (2, "u", "<article><p>A text, which is long enough to be one.</p></article>")], "page_id long, url string, html string").withColumn("text", F.lit(1))
    got = html_extract.extracted(pages).collect()
    assert len(got) == 4 and sum(r.n_chars for r in got) == 2 * 39 and html_extract.extracted(pages.limit(0)).count() == 0
    e = spark.read.parquet(f"{SF}/embeddings.parquet").withColumn("rep", F.lit(1)).withColumn("score", F.lit(1))
    assert ann.neighbours(e.limit(0), F.col("vec_id") % 50 == 0).count() == 0
    assert ann.neighbours(e.filter("vec_id = 0"), F.col("vec_id") % 50 == 0).count() == 0  # no other row


def test_given_pages_give_their_articles():
    """All pages of a table: the article's headings and paragraphs by a plain pattern."""
    import html as h

    import pyarrow.parquet as pq

    field = html_extract.standard_field()
    for page in pq.read_table("/root/testdata/sf0.01/pages.parquet").column("html").to_pylist():
        article = "".join(re.findall(r"(?s)<article\b[^>]*>(.*?)</article>", page))
        blocks = [re.sub(r"\s+", " ", h.unescape(re.sub(r"<[^>]*>", "", b))).strip() for b in re.findall(r"(?s)<(?:h1|p)\b[^>]*>(.*?)(?=</?(?:h1|p)\b|$)", article)]
        assert html_extract.main_text(page, field) == "\n\n".join(b for b in blocks if b)


def test_hostile_pages_take_linear_time():
    field, n = html_extract.standard_field(), 100_000
    for page in ("<a " * n, '<a "' * n + ">", '<p class="x' * n + ">", "<svg>" * n, "<!--" * n, "<!x" * n, "<li>" * n + "x", "< " * n, "<p class=" + "ab-" * n + ">x</p>"):
        t = time.perf_counter()
        html_extract.main_text(page, field)
        assert time.perf_counter() - t < 10, page[:12]


def test_whole_lines_and_true_windows():
    score = toxicity.Scorer(toxicity.Model({"scum": 4.0}))
    at = {name: k for k, name in enumerate(toxicity.FEATURES)}
    for gap in (190, 260, 5000):
        assert score.features('He "' + "x" * gap + ' scum" there')[at["quoted"]] == 1.0
    long = "y" * 300
    assert score.features(f"you {long} {long} scum")[at["addressed"]] == 1.0
    assert score.features("you " + "a b c d e f " + "scum")[at["addressed"]] == 0.0
    assert score.entry("scum***") == ("scum", 0) and score.entry("scumming") is None


def test_hubs_and_chains_have_right_components(spark, monkeypatch):
    monkeypatch.setattr(graph, "HUB", 20)
    pairs = [(1000, k) for k in range(100, 400)] + [(k, k + 1) for k in range(500, 560)] + [(7, 7), (560, 1000)]
    got = {r.node: r.root for r in graph.components(spark.createDataFrame(pairs, "u long, v long")).collect()}
    assert set(got.values()) == {100} and len(got) == 300 + 61 + 1


def test_repeated_rows_are_dealt_apart(spark, monkeypatch):
    monkeypatch.setattr(pfair, "REPEATS", 50)
    rows = spark.range(3000).selectExpr("if(id < 2000, 5, id) AS doc_id", "'same' AS text", "'a' AS source")
    got = pfair.mixed(rows).collect()
    assert len(got) == 3000 and max(Counter((r.block, r.row_in_block) for r in got).values()) == 1
    made = packing.packed(rows, shard_rows=100)
    assert made.count() == 3000 and made.groupBy("shard").count().agg(F.max("count")).first()[0] < 300


def test_weights_below_one_are_refused(spark):
    with pytest.raises(Exception, match="parts must be 1 or more"):
        pfair.period_plan(spark.createDataFrame([("a", 0), ("b", 3)], "source string, parts long")).collect()
