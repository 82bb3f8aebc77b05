"""Chunking: semantic runs of sentences, and the fixed granularities they compete with.

A chunk goes on while the cosine of neighbouring sentences (hashed token counts)
is at least a threshold, given as a fraction and compared in integers.  Two
plans give the same rows: ``semantic_chunks`` sweeps each document inside one
Arrow pass without any shuffle (the plan for large corpora), and
``semantic_chunks_windowed`` states it with joins and windows.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from fractions import Fraction
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from litspark.functions.text import DIMS, sentences, sparse_features, split_sentences, split_tokens, token_array, token_code, token_codes

THRESHOLD = Fraction(1, 10)
#: Sentences whose counts are held at a time (a longer document is held whole), and sizes up to which products stay exact in 64 bits.
HELD_SENTENCES = 4096
EXACT_SIZE, EXACT_PART = 2**24, 128
CHUNK_SCHEMA = "chunk_id string, doc_id long, chunk_no int, sent_from int, sent_to int, text string, n_tokens int"


def joins(dot: int, left: int, right: int, threshold: Fraction) -> bool:
    """cos >= threshold for exact integers: dot product and squared norms; zero vectors never join."""
    num, den = threshold.numerator, threshold.denominator
    if num <= 0:
        return left * right > 0 or num < 0
    return left * right > 0 and dot * dot * den * den >= num * num * left * right


def cut(sentence_list: list[str], threshold: Fraction = THRESHOLD, dims: int = DIMS, max_tokens: int | None = None, centroid: bool = False) -> list[tuple[int, int, int]]:
    """(first sentence, last sentence, tokens) of each chunk.

    ``max_tokens`` ends a chunk before the sentence that would exceed it (a longer
    sentence is a chunk of its own); ``centroid`` compares a sentence with the sum
    of its chunk so far in place of the sentence before it.
    """
    out: list[list[int]] = []
    before: Counter = Counter()
    size_before = 0
    for i, sentence in enumerate(sentence_list):
        codes = [token_code(w) % dims for w in split_tokens(sentence)]
        counts = Counter(codes)
        size = sum(c * c for c in counts.values())
        fits = max_tokens is None or (out and out[-1][2] + len(codes) <= max_tokens)
        if out and fits and joins(sum(c * before[d] for d, c in counts.items()), size_before, size, threshold):
            out[-1][1] = i
            out[-1][2] += len(codes)
            if centroid:
                counts.update(before)
                size = sum(c * c for c in counts.values())
        else:
            out.append([i, i, len(codes)])
        before, size_before = counts, size
    return [tuple(c) for c in out]


def _held(ids: list, texts: list) -> Iterator[tuple[list, list[list[str]]]]:
    """Documents and their sentences, some thousands of sentences at a time."""
    names, said, n = [], [], 0
    for doc_id, text in zip(ids, texts):
        own = split_sentences(text)
        if n and n + len(own) > HELD_SENTENCES:
            yield names, said
            names, said, n = [], [], 0
        names.append(doc_id)
        said.append(own)
        n += len(own)
    yield names, said


def _cuts_and_words(said: list[list[str]], threshold: Fraction, dims: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, list[list[str]]]:
    """Of all sentences of some documents in one list: where chunks begin, the first sentence of each sentence's document, token counts, counts by dimension, and tokens.

    The same as ``cut`` of each document, by whole arrays.
    """
    sizes = np.array([len(s) for s in said])
    words = [split_tokens(s) for own in said for s in own]
    codes = [token_codes(w) for w in words]
    n, tokens = len(codes), np.array([len(c) for c in codes], np.int64)
    flat = np.fromiter(chain.from_iterable(codes), np.int64, int(tokens.sum())) % dims
    counts = np.bincount(np.repeat(np.arange(n) * dims, tokens) + flat, minlength=n * dims).reshape(n, dims)
    size, dot = (counts * counts).sum(axis=1), np.zeros(n, np.int64)
    dot[1:] = (counts[1:] * counts[:-1]).sum(axis=1)
    before = np.append(0, size[:-1])[:n]
    num, den = threshold.numerator, threshold.denominator
    if 0 < num and max(num, den) <= EXACT_PART and size.max(initial=0) < EXACT_SIZE:
        goes_on = (before * size > 0) & (dot * dot * (den * den) >= before * size * (num * num))
    else:
        goes_on = np.array([joins(d, a, b, threshold) for d, a, b in zip(dot.tolist(), before.tolist(), size.tolist())], bool)
    firsts = np.cumsum(sizes) - sizes
    goes_on[firsts[sizes > 0]] = False
    return np.flatnonzero(~goes_on), np.repeat(firsts, sizes), tokens, counts, words


def _cuts(said: list[list[str]], threshold: Fraction, dims: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    return _cuts_and_words(said, threshold, dims)[:4]


def semantic_chunks(docs: DataFrame, threshold: Fraction = THRESHOLD, dims: int = DIMS, max_tokens: int | None = None, centroid: bool = False) -> DataFrame:
    """Chunks of ``docs(doc_id, text)`` in one pass over each row: no shuffle; ``max_tokens`` and ``centroid`` as in ``cut``."""

    def rows_of(ids: list, texts: list) -> Iterator[tuple]:
        for names, said in _held(ids, texts):
            if max_tokens is None and not centroid:
                starts, firsts, tokens, _ = _cuts(said, threshold, dims)
                ends, begun = np.append(starts[1:], len(tokens)), firsts[starts]
                found = np.add.reduceat(tokens, starts) if len(starts) else starts
                chunks = iter(zip((starts - begun).tolist(), (ends - begun - 1).tolist(), found.tolist(), begun.tolist()))
                one, at = next(chunks, None), 0
                for doc_id, own in zip(names, said):
                    no = 0
                    while one and one[3] == at and no < len(own):
                        yield doc_id, no, *one[:3], own
                        one, no = next(chunks, None), no + 1
                    at += len(own)
            else:
                for doc_id, own in zip(names, said):
                    for no, found in enumerate(cut(own, threshold, dims, max_tokens, centroid)):
                        yield doc_id, no, *found, own

    def sweep(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            out = [
                (f"{doc_id}-{no}", doc_id, no, first, last, ". ".join(said[first : last + 1]), n)
                for doc_id, no, first, last, n, said in rows_of(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist())
            ]
            columns = list(zip(*out)) or [()] * 7
            kinds = (pa.string(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.string(), pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], ["chunk_id", "doc_id", "chunk_no", "sent_from", "sent_to", "text", "n_tokens"])

    return docs.select("doc_id", "text").mapInArrow(sweep, CHUNK_SCHEMA)


def _names(names: list, said: list[list[str]], starts: np.ndarray, firsts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Document and number of each chunk."""
    begun = firsts[starts]
    return np.repeat(np.array(names, np.int64), [len(s) for s in said])[starts], np.arange(len(starts)) - np.searchsorted(begun, begun)


def chunk_words(ids: list, texts: list, threshold: Fraction = THRESHOLD, dims: int = DIMS) -> Iterator[tuple[np.ndarray, list[str], np.ndarray]]:
    """(ids, tokens, tokens of each chunk) of the ``semantic_chunks`` of some documents, block by block; an id is 100,000 times the document and the chunk's number."""
    for names, said in _held(ids, texts):
        starts, firsts, tokens, _, words = _cuts_and_words(said, threshold, dims)
        if len(starts):
            doc, no = _names(names, said, starts, firsts)
            yield doc * 100_000 + no, list(chain.from_iterable(words)), np.add.reduceat(tokens, starts)


def chunk_vectors(docs: DataFrame, threshold: Fraction = THRESHOLD, dims: int = DIMS) -> DataFrame:
    """(doc_id, chunk_no, vector) of ``semantic_chunks``: the hashed counts of each chunk, summed from those of its sentences; no text is written or read again."""

    def sweep(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            for names, said in _held(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()):
                starts, firsts, _, counts = _cuts(said, threshold, dims)
                if not len(starts):
                    continue
                ids, no = _names(names, said, starts, firsts)
                flat = pa.array(np.add.reduceat(counts, starts).astype(np.float32).ravel(), pa.float32())
                vectors = pa.ListArray.from_arrays(pa.array(np.arange(len(starts) + 1, dtype=np.int32) * dims), flat)
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(no.astype(np.int32)), vectors], ["doc_id", "chunk_no", "vector"])

    return docs.select("doc_id", "text").mapInArrow(sweep, "doc_id long, chunk_no int, vector array<float>")


def adjacent_similarity(docs: DataFrame, dims: int = DIMS) -> DataFrame:
    """(doc_id, sent_no, sentence, dot, n1, n2) of each sentence with the one before it; null before the first."""
    said = sentences(docs)
    features = sparse_features(said, ["doc_id", "sent_no"], "sentence", dims)
    sizes = features.groupBy("doc_id", "sent_no").agg(F.sum(F.col("w") * F.col("w")).alias("n"))
    previous = features.select("doc_id", (F.col("sent_no") + 1).alias("sent_no"), "dim", F.col("w").alias("v"))
    dots = features.join(previous, ["doc_id", "sent_no", "dim"]).groupBy("doc_id", "sent_no").agg(F.sum(F.col("w") * F.col("v")).alias("dot"))
    order = Window.partitionBy("doc_id").orderBy("sent_no")
    sized = said.join(sizes, ["doc_id", "sent_no"], "left").join(dots, ["doc_id", "sent_no"], "left")
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long")
    return sized.select("doc_id", "sent_no", "sentence", zero(F.col("dot")).alias("dot"), zero(F.lag("n").over(order)).alias("n1"), zero(F.col("n")).alias("n2"))


def semantic_chunks_windowed(docs: DataFrame, threshold: Fraction = THRESHOLD, dims: int = DIMS) -> DataFrame:
    """The same chunks from joins and windows, as the reference for the one-pass plan (0 < threshold)."""
    num, den = threshold.numerator, threshold.denominator
    go_on = (F.col("n1") * F.col("n2") > 0) & (F.col("dot") * F.col("dot") * (den * den) >= F.col("n1") * F.col("n2") * (num * num))
    order = Window.partitionBy("doc_id").orderBy("sent_no")
    numbered = adjacent_similarity(docs, dims).withColumn("chunk_no", (F.sum(F.when((F.col("sent_no") > 0) & go_on, 0).otherwise(1)).over(order) - 1).cast("int"))
    grouped = numbered.groupBy("doc_id", "chunk_no").agg(
        F.min("sent_no").alias("sent_from"), F.max("sent_no").alias("sent_to"),
        F.array_sort(F.collect_list(F.struct("sent_no", "sentence"))).alias("s"), F.sum(F.size(token_array(F.col("sentence")))).cast("int").alias("n_tokens"),
    )
    return grouped.select(
        F.concat_ws("-", "doc_id", "chunk_no").alias("chunk_id"), "doc_id", "chunk_no", "sent_from", "sent_to",
        F.array_join(F.transform("s", lambda x: x["sentence"]), ". ").alias("text"), "n_tokens",
    )


def fixed_chunks(docs: DataFrame, size: int = 128, overlap: int = 32) -> DataFrame:
    """Runs of ``size`` tokens, each starting ``size - overlap`` after the last; the tail is shorter."""
    step = size - overlap
    if step <= 0:
        raise ValueError("overlap must be smaller than size")
    words = docs.select("doc_id", token_array(F.coalesce("text", F.lit(""))).alias("w")).where("size(w) > 0")
    starts = F.sequence(F.lit(0), F.greatest(F.ceil((F.size("w") - overlap) / step) - 1, F.lit(0)).cast("int"))
    return words.select("doc_id", "w", F.explode(starts).alias("chunk_no")).select(
        "doc_id", "chunk_no", F.size(F.slice("w", F.col("chunk_no") * step + 1, size)).alias("n_tokens"), F.array_join(F.slice("w", F.col("chunk_no") * step + 1, size), " ").alias("text")
    )


def granularity_chunks(docs: DataFrame, granularity: str) -> DataFrame:
    """Sentences, paragraphs or whole documents as chunks: (doc_id, chunk_no, text)."""
    cuts: dict[str, Column] = {
        "sentence": sentence_list(F.col("text")),
        "paragraph": F.filter(F.split(F.coalesce("text", F.lit("")), "\n+"), lambda s: s.rlike(r"\S")),
        "document": F.filter(F.array(F.coalesce("text", F.lit(""))), lambda s: s.rlike(r"\S")),
    }
    return docs.select("doc_id", F.posexplode(cuts[granularity]).alias("chunk_no", "text"))


def sentence_list(text: Column) -> Column:
    from litspark.functions.text import sentence_array

    return sentence_array(text)
