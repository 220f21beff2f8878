"""Registered queries of the corpus operators, each over its whole table, and their SQL where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stseq.llm import decontam, hilbert, html, langid, licenses, lm, packing, pipeline, simhash, spotsigs, urlrep
from stseq.llm.common import read_table


def op1_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm.score_texts(read_table(spark, sf_dir, "documents"))


def op2_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract_main(read_table(spark, sf_dir, "pages"))


def op3_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan_licenses(read_table(spark, sf_dir, "documents"))


def op4_spot_signatures(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spotsigs.fingerprint_documents(read_table(spark, sf_dir, "documents"))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents (doc_id) and pages (page_id) judged by one text model, each with the evidence of its own table."""
    docs = read_table(spark, sf_dir, "documents")
    model = langid.fit_text_model(docs)
    none = F.lit(None).cast("bigint")
    of_docs = langid.identify(langid.document_rows(docs), model)
    of_pages = langid.identify(langid.page_texts(read_table(spark, sf_dir, "pages")), model)
    told = ["declared", "language", "posterior", "text_language"]
    return of_docs.select("doc_id", none.alias("page_id"), *told).unionByName(of_pages.select(none.alias("doc_id"), "page_id", *told))


def op6_hilbert_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hilbert.shard_documents(read_table(spark, sf_dir, "documents"))


def op7_cost_balanced_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(read_table(spark, sf_dir, "documents"))


def op8_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contaminated(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read_table(spark, sf_dir, "pages")
    return urlrep.filter_urls(pages, urlrep.labelled_outcomes(pages, read_table(spark, sf_dir, "labels")))


def op10_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.simhash_components(read_table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = (
        op1_lm_scoring, op2_html_extraction, op3_license_scan, op4_spot_signatures, op5_language_id, op6_hilbert_sharding,
        op7_cost_balanced_packing, op8_benchmark_decontamination, op9_url_filter, op10_simhash_near_dedup,
    )
    return {f.__name__: f for f in found} | {"pipeline": pipeline.run}


def oracle_sql() -> dict[str, str]:
    return {"op9_url_filter": urlrep.oracle_sql()}
