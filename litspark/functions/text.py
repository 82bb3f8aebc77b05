"""Portable text primitives: the same result in Spark, SQL and plain Python.

Sentences end at ``[.!?]+`` before white space and at line ends; tokens are
lower-case runs of letters and digits; a token's feature is its md5 (first six
hex digits) modulo the number of dimensions.  Counts are integers, so dot
products and norms are exact.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable

import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SENTENCE_END = r"[.!?]+\s+|\n+"
TOKEN_GAP = r"[^\p{L}\p{N}]+"
#: Dimensions of the untuned hashed encoder.
DIMS = 64

_end, _gap = re.compile(SENTENCE_END, re.A), regex.compile(TOKEN_GAP)
#: Tokens of texts below U+0250, where both libraries know the same letters and digits; this one is several times faster.
_word, _beyond = re.compile(r"[^\W_]+"), re.compile("[^\x00-\u024f]")
#: Remembered codes of tokens; the table starts anew when full.
REMEMBERED = 400_000


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use(value)`` with ``value`` computed once, even where ``use`` names it inside a lambda of its own."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def sentence_array(text: Column) -> Column:
    return F.filter(F.split(F.coalesce(text, F.lit("")), SENTENCE_END), lambda s: s.rlike(r"\S"))


def token_array(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), TOKEN_GAP), lambda w: w != "")


def hash_code(token: Column) -> Column:
    """24 bits of a token's md5."""
    return F.conv(F.substring(F.md5(token), 1, 6), 16, 10).cast("int")


def sentences(docs: DataFrame) -> DataFrame:
    """(doc_id, sent_no, sentence), sent_no from 0."""
    return docs.select("doc_id", F.posexplode(sentence_array(F.col("text"))).alias("sent_no", "sentence"))


def sparse_features(rows: DataFrame, keys: list[str], text: str, dims: int = DIMS) -> DataFrame:
    """(keys, dim, w): how many tokens of ``text`` fall on each dimension."""
    tokens = rows.select(*keys, F.explode(token_array(F.col(text))).alias("token"))
    return tokens.select(*keys, (hash_code(F.col("token")) % dims).alias("dim")).groupBy(*keys, "dim").agg(F.count("*").alias("w"))


def split_sentences(text: str | None) -> list[str]:
    return [s for s in _end.split(text or "") if s.strip(" \t\n\r\x0b\x0c")]


def split_tokens(text: str) -> list[str]:
    text = text.lower()
    return [w for w in _gap.split(text) if w] if _beyond.search(text) else _word.findall(text)


class _Codes(dict):
    def __missing__(self, token: str) -> int:
        if len(self) >= REMEMBERED:
            self.clear()
        code = self[token] = int.from_bytes(hashlib.md5(token.encode()).digest()[:3], "big")
        return code


_codes = _Codes()


def token_code(token: str) -> int:
    return _codes[token]


def token_codes(tokens: list[str]) -> list[int]:
    return list(map(_codes.__getitem__, tokens))


# SQL twins, as common table expressions over ``documents``.
SQL_SENTENCES = r"""
sent_lists AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[.!?]+\s+|\n+'), lambda x: regexp_matches(x, '\S')) AS s FROM documents),
sent AS (SELECT doc_id, unnest(s) AS sentence, (generate_subscripts(s, 1) - 1)::INT AS sent_no FROM sent_lists)"""


def sql_tokens(text: str) -> str:
    return rf"list_filter(regexp_split_to_array(lower({text}), '[^\p{{L}}\p{{N}}]+'), lambda y: y <> '')"


def sql_code(token: str) -> str:
    return f"('0x' || substr(md5({token}), 1, 6))::INT"


def sql_features(rows: str, keys: str, text: str, dims: int = DIMS) -> str:
    return f"(SELECT {keys}, ({sql_code('tok')} % {dims})::INT AS dim, count(*) AS w FROM (SELECT {keys}, unnest({sql_tokens(text)}) AS tok FROM {rows}) GROUP BY ALL)"
