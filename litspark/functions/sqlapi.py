"""SQL functions: cosine, late interaction, character accuracy, embedding, and table functions for chunks and regions."""

from __future__ import annotations

from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from litspark.functions.text import split_sentences, split_tokens, token_code
from litspark.operators.chunk import cut
from litspark.operators.parse import regions

COSINE = """CREATE OR REPLACE TEMPORARY FUNCTION rag_cosine(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE
RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v)
  / (sqrt(aggregate(transform(a, x -> x * x), 0D, (s, v) -> s + v)) * sqrt(aggregate(transform(b, x -> x * x), 0D, (s, v) -> s + v)))"""
CAR = """CREATE OR REPLACE TEMPORARY FUNCTION rag_car(ref STRING, hyp STRING) RETURNS DOUBLE
RETURN CASE WHEN length(ref) = 0 THEN IF(length(hyp) = 0, 1D, 0D) ELSE greatest(0D, 1D - levenshtein(ref, hyp) / length(ref)) END"""


@F.pandas_udf("array<float>")
def rag_embed(texts: pd.Series) -> pd.Series:
    def embed(text: str | None) -> np.ndarray:
        out = np.zeros(64, np.float32)
        np.add.at(out, [token_code(w) % 64 for w in split_tokens(text or "")], 1)
        return out

    return texts.map(embed)


@F.udtf(returnType="chunk_no int, sent_from int, sent_to int, text string")
class SemanticChunks:
    def eval(self, text: str, threshold: float) -> Iterator[tuple]:
        said = split_sentences(text)
        for no, (first, last, _) in enumerate(cut(said, Fraction(threshold).limit_denominator(1000))):
            yield no, first, last, ". ".join(said[first : last + 1])


@F.udtf(returnType="region_no int, kind string, role string, text string")
class Regions:
    def eval(self, html: str) -> Iterator[tuple]:
        for no, kind, role, text, _, _ in regions(html):
            yield no, kind, role, text


def register_all(spark: SparkSession) -> None:
    """Register the functions on a session; the SQL-bodied ones are inlined by the optimizer."""
    spark.sql(COSINE)
    spark.sql(CAR)
    spark.udf.register("rag_embed", rag_embed)
    spark.udtf.register("rag_chunks", SemanticChunks)
    spark.udtf.register("rag_regions", Regions)
