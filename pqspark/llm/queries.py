"""The registered queries of this subpackage, one per operator, each over its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pqspark.llm import ann, html_extract, jaccard_join, line_dedup, lm_scoring, media, packing, pfair, token_tables, toxicity


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    good = _table(spark, sf_dir, "labels").filter("quality = 1 and toxic = 0").select("doc_id")
    made = lm_scoring.scored(_table(spark, sf_dir, "documents"), good)
    return made.select("doc_id", "n_tokens", *(F.round(c, 6).alias(c) for c in ("target_loss", "background_loss", "difference")))


def op6_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extracted(_table(spark, sf_dir, "pages"))


def op10_cross_polytope(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.neighbours(_table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0, k=5)


def op2_token_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_tables.encoded(_table(spark, sf_dir, "documents"))


def op4_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.digested(_table(spark, sf_dir, "documents"))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    return toxicity.scored(docs, toxicity.fit(docs, _table(spark, sf_dir, "labels")))


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(_table(spark, sf_dir, "documents"))


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.without_boilerplate(_table(spark, sf_dir, "documents")).select("doc_id", "n_lines", "n_dropped", "text")


def op9_pfair_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pfair.mixed(_table(spark, sf_dir, "documents").select("doc_id", F.coalesce("source", F.lit("")).alias("source")))


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.jaccard_components(_table(spark, sf_dir, "documents"), width=4, num=85, den=100)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_lm_scoring": op1_lm_scoring,
        "op6_html_extraction": op6_html_extraction,
        "op10_cross_polytope": op10_cross_polytope,
        "op2_token_tables": op2_token_tables,
        "op4_media_columns": op4_media_columns,
        "op3_toxicity": op3_toxicity,
        "op5_best_fit_packing": op5_best_fit_packing,
        "op7_line_dedup": op7_line_dedup,
        "op9_pfair_mix": op9_pfair_mix,
        "op8_jaccard_join": op8_jaccard_join,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_lm_scoring": lm_scoring.ORACLE, "op7_line_dedup": line_dedup.ORACLE, "op9_pfair_mix": pfair.ORACLE}
