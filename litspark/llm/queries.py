"""The registered queries of this subpackage: name -> callable, and SQL where SQL can express the result."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from litspark.llm.bpe import bpe_encode
from litspark.llm.common import read
from litspark.llm.decontamination import ORACLE as LEAKS_ORACLE
from litspark.llm.decontamination import leaks
from litspark.llm.html_extract import ORACLE as PAGES_ORACLE
from litspark.llm.html_extract import extract_pages
from litspark.llm.license_scan import license_report
from litspark.llm.license_scan import oracle as license_oracle
from litspark.llm.near_dedup import ORACLE as NEAR_ORACLE
from litspark.llm.near_dedup import near_duplicates
from litspark.llm.quality_rules import quality_verdicts
from litspark.llm.secret_scan import secret_report
from litspark.llm.substring_dedup import ORACLE as SUBSTRING_ORACLE
from litspark.llm.substring_dedup import substring_dedup
from litspark.llm.token_count import token_counts
from litspark.llm.tool_calls import ORACLE as DIALOGUE_ORACLE
from litspark.llm.tool_calls import dialogue_events, link_tool_calls


def op1_tool_call_linking(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_tool_calls(*dialogue_events(read(spark, sf_dir, "conversations")))


def op2_fst_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(read(spark, sf_dir, "documents"))


def op3_forest_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_report(read(spark, sf_dir, "documents"))


def op4_simhash_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark")).drop("tag").distinct()


def op5_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(read(spark, sf_dir, "documents")).drop("tag")


def op6_mcd_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_verdicts(read(spark, sf_dir, "documents")).drop("tag")


def op7_license_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_report(read(spark, sf_dir, "documents"))


def op8_segment_tree_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_encode(read(spark, sf_dir, "documents"), with_ids=False)


def op9_crf_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(read(spark, sf_dir, "pages"))


def op10_rlz_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup(read(spark, sf_dir, "documents"), with_text=False)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_tool_call_linking": op1_tool_call_linking,
    "op2_fst_token_counts": op2_fst_token_counts,
    "op3_forest_secret_scan": op3_forest_secret_scan,
    "op4_simhash_decontamination": op4_simhash_decontamination,
    "op5_minhash_near_dedup": op5_minhash_near_dedup,
    "op6_mcd_quality_rules": op6_mcd_quality_rules,
    "op7_license_rules": op7_license_rules,
    "op8_segment_tree_bpe": op8_segment_tree_bpe,
    "op9_crf_html_extraction": op9_crf_html_extraction,
    "op10_rlz_substring_dedup": op10_rlz_substring_dedup,
}

ORACLES: dict[str, str] = {
    "op1_tool_call_linking": DIALOGUE_ORACLE,
    "op4_simhash_decontamination": LEAKS_ORACLE,
    "op5_minhash_near_dedup": NEAR_ORACLE,
    "op7_license_rules": license_oracle(),
    "op9_crf_html_extraction": PAGES_ORACLE,
    "op10_rlz_substring_dedup": SUBSTRING_ORACLE,
}
