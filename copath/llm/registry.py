"""Queries of the operators over their whole tables, and SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from copath.llm import decontaminate, embeddings, hmm, html, lines, pieces, simhash, substring, toxicity, warc
from copath.llm.store import read_table


def op1_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links, component and representative of every vector."""
    return embeddings.groups(read_table(spark, sf_dir, "embeddings"))


def op2_hmm_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact log10 likelihood of every document under a hidden Markov model, beside the unigram base score."""
    return hmm.score(read_table(spark, sf_dir, "documents"))


def op3_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, fingerprint (hex), component_id of every document; links at 4 or fewer differing bits."""
    found = simhash.near_duplicates(read_table(spark, sf_dir, "documents"))
    return found.selectExpr("id AS doc_id", "lower(lpad(hex(fp), 16, '0')) AS fingerprint", "component_id")


def op4_warc_derivatives(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Metadata and conversion records of every page's response."""
    return warc.report(read_table(spark, sf_dir, "pages"))


def op5_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of every page."""
    return html.report(read_table(spark, sf_dir, "pages"))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity score of every document, learnt from the labelled ones that aren't held out."""
    return toxicity.report(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op7_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hit words and items of every document against windows of ten benchmark words."""
    return decontaminate.report(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What is left of every document without lines that are within one word edit of an earlier line."""
    return lines.report(read_table(spark, sf_dir, "documents"))


def op9_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Piece counts, score, digest of the piece ids and round trip of every document."""
    return pieces.report(read_table(spark, sf_dir, "documents"))


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What is left of every document without windows of 13 words that an earlier document starts too."""
    return substring.report(read_table(spark, sf_dir, "documents"))


QUERIES = {
    "op1_embedding_near_dedup": op1_embedding_near_dedup,
    "op2_hmm_language_model": op2_hmm_language_model,
    "op3_simhash_near_dedup": op3_simhash_near_dedup,
    "op4_warc_derivatives": op4_warc_derivatives,
    "op5_html_extraction": op5_html_extraction,
    "op6_toxicity": op6_toxicity,
    "op7_benchmark_decontamination": op7_benchmark_decontamination,
    "op8_line_dedup": op8_line_dedup,
    "op9_sentencepiece": op9_sentencepiece,
    "op10_substring_dedup": op10_substring_dedup,
}
ORACLES: dict[str, str] = {}
