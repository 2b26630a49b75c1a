"""The queries of this subpackage and the DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import ann, decontaminate, html_text, licenses, mixing, ngram_join, quality, secrets, url_filter, warc
from .common import cut, table
from .oracles import ORACLES as ORACLES  # DuckDB SQL, for those that SQL can express


def op1_license_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Licences found in every whole text of documents. Edge cases as in the operator."""
    return licenses.scan_licenses(table(spark, sf_dir, "documents"))


def op2_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The verdict on every url of pages. Edge cases as in the operator."""
    return url_filter.judge_urls(table(spark, sf_dir, "pages"))


def op3_warc_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Archives of all pages, written and read back. Edge cases as in the operator."""
    return warc.round_trip(table(spark, sf_dir, "pages"))


def op4_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Occurrences of benchmark items in all documents. Edge cases as in the operator."""
    return decontaminate.contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op5_robust_graph_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The nearest rows of every twentieth embedding. Edge cases as in the operator."""
    return ann.search(table(spark, sf_dir, "embeddings"))


def op6_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of every page. Edge cases as in the operator."""
    return html_text.extract_main_text(table(spark, sf_dir, "pages"))


def op7_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality score of every document. Edge cases as in the operator."""
    return quality.score_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near-duplicate class of every document. Edge cases as in the operator."""
    return ngram_join.jaccard_components(table(spark, sf_dir, "documents"))


def op9_mixing_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words that the mix takes of every document. Edge cases as in the operator."""
    return mixing.mix(table(spark, sf_dir, "documents"))


def op10_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Secrets in every whole text of documents. Edge cases as in the operator."""
    return secrets.find_secrets(table(spark, sf_dir, "documents"))


def secret_ledger_increment(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same findings in two runs: one with the base rules, whose ledger the second reads, which scans for the other rules only."""
    docs = table(spark, sf_dir, "documents")
    ledger = cut(secrets.update_ledger(docs, None, tuple(r for r in secrets.RULES if r.base)))
    return secrets.find_secrets(docs, ledger)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_license_scans": op1_license_scans,
    "op2_url_filters": op2_url_filters,
    "op3_warc_revisits": op3_warc_revisits,
    "op4_benchmark_decontamination": op4_benchmark_decontamination,
    "op5_robust_graph_search": op5_robust_graph_search,
    "op6_html_extraction": op6_html_extraction,
    "op7_quality_classifier": op7_quality_classifier,
    "op8_ngram_jaccard_join": op8_ngram_jaccard_join,
    "op9_mixing_sources": op9_mixing_sources,
    "op10_secret_scans": op10_secret_scans,
    "secret_ledger_increment": secret_ledger_increment,
}