"""Corpus pipeline: quality rules, near-duplicates, benchmark decontamination, secret scans, BPE.

Each stage works on all documents that the one before kept and was written as
Parquet.  Rejected documents, all but one of a group of near-duplicates and
documents that hold a benchmark passage go; secrets are replaced in the text;
the last stage turns texts into token ids.

Edge cases, for every stage: rows are named by doc_id and the hash of their text,
nulls being values, so repeated doc_ids and null doc_ids are told apart; null and
empty texts fail the quality rules, and where a stage meets them all the same
they are kept as they are; an empty table stays empty; extra columns, whatever
their names, are carried unchanged up to the last stage, which returns its own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from litspark.llm.bpe import bpe_encode
from litspark.llm.common import Scratch, drop_rows, read, scratches
from litspark.llm.decontamination import leaks
from litspark.llm.near_dedup import keep_one
from litspark.llm.quality_rules import quality_verdicts
from litspark.llm.secret_scan import scan_secrets


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep."""
    return drop_rows(docs, quality_verdicts(docs).where("not kept").select("doc_id", "tag"))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates."""
    return keep_one(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a benchmark passage."""
    return drop_rows(docs, leaks(docs, read(spark, sf_dir, "benchmark")).select("doc_id", "tag"))


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with secrets in their texts replaced and n_chars following the text."""
    # the row travels as one column, so that its names cannot meet those of the scan
    done = scan_secrets(docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), "text"))
    changed = F.size("findings") > 0
    new = {"text": F.col("redacted")}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(changed, F.char_length("redacted").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("row")["n_chars"])
    return done.select(*[new.get(c, F.col("row")[c]).alias(c) for c in docs.columns])


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of all documents, with digests of the ids and of the text decoded from them."""
    return bpe_encode(docs)


STAGES = [("quality", quality), ("near_dedup", near_dedup), ("decontaminate", decontaminate), ("secrets", secrets), ("encode", encode)]

#: The robust estimates, components and token ids are beyond SQL; tests hold the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows; every stage before it is written and read again, and its own tables go."""
    kept = Scratch(spark, "pipeline")
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        with scratches() as made:
            docs = kept.write(stage(spark, docs, sf_dir), name)
        for scratch in made:
            scratch.close()
    return STAGES[-1][1](spark, docs, sf_dir)
