"""Exact search of hashed counts: the rows of ``knn_gemm`` over ``hashed_vectors`` without a product of matrices.

A question has a handful of tokens, so few of its counts are not zero.  Its
scores are the sum of as many rows of the transposed unit vectors, and questions
that begin alike, in the order of how many questions have a count, share the sums
so far: with questions of one form there are one or two sums for each.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from functools import reduce
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from litspark.functions.text import split_tokens, token_codes
from litspark.functions.vectors import unit
from litspark.operators.encode import hashed_vectors
from litspark.operators.index import RANKED, SLICES, _Kept, knn_gemm, rank

#: Passages that a task scores at a time, pieces of them whose best are compared, and passages that are counted at a time.
HELD, PIECES, READ = 2**15, 64, 4096
#: Questions that go to every task; larger sets take a pass for each as many.
ASKED = 100_000


def codes(texts: DataFrame, text: str, key: str, dims: int) -> DataFrame:
    """(id, code): the places and sizes of the counts of each text that are not zero, as bytes; equal vectors have equal codes."""

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = (sorted(Counter(c % dims for c in token_codes(split_tokens(t or ""))).items()) for t in batch.column("text").to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array([np.array(f, np.uint32).tobytes() for f in found], pa.binary())], ["id", "code"])

    return texts.select(F.col(key).cast("long").alias("id"), F.col(text).cast("string").alias("text")).mapInArrow(encode, "id long, code binary")


def _counts(texts: list[str | None], dims: int) -> np.ndarray:
    words = [split_tokens(t or "") for t in texts]
    at = np.repeat(np.arange(len(words)) * dims, [len(w) for w in words])
    return np.bincount(at + np.array(token_codes(list(chain.from_iterable(words))), np.int64) % dims, minlength=len(words) * dims).reshape(-1, dims)


class _Paths:
    """Questions in an order in which neighbours share sums, and the best ``k`` passages of each."""

    def __init__(self, names: np.ndarray, found: list[bytes], k: int, dims: int):
        self.k, self.dims, self.kept = k, dims, _Kept(k)
        steps = [[tuple(p) for p in np.frombuffer(c, np.uint32).reshape(-1, 2).tolist()] for c in found]
        often = Counter(chain.from_iterable(steps))
        self.asked = []
        for name, path in zip(names.tolist(), steps):
            size = sum(c * c for _, c in path) ** 0.5
            places, unit_counts = np.array([p for p, _ in path], np.int64), np.array([c for _, c in path], np.float64) / (size or 1)
            self.asked.append((sorted(path, key=lambda p: (-often[p], p)), name, size, places, unit_counts))
        self.asked.sort(key=lambda x: x[:2])

    def add(self, ids: np.ndarray, counts: np.ndarray) -> None:
        n, k, digits = len(ids), self.k, 10.0**-self.kept.digits
        norm, w = np.empty((n, 1)), np.empty((self.dims, n), np.float32)
        for low in range(0, n, READ):
            part = counts[low : low + READ].astype(np.float64)
            norm[low : low + READ] = np.linalg.norm(part, axis=1, keepdims=True)
            w[:, low : low + READ] = unit(part).T
        norm[norm == 0] = 1  # passages without tokens
        u, sums, before, wide = np.zeros((1, self.dims)), [np.zeros(n, np.float32)], [], n // PIECES
        for path, name, size, places, unit_counts in self.asked:
            at = 0
            while at < len(before) and at < len(path) and before[at] == path[at]:
                at += 1
            before = path
            for place, count in path[at:]:
                if len(sums) == at + 1:
                    sums.append(np.empty(n, np.float32))
                np.add(sums[at], w[place] if count == 1 else w[place] * np.float32(count), out=sums[at + 1])
                at += 1
            s = sums[at]
            if not size:
                self.kept._merge(name, np.zeros(n), ids)
                continue
            slack = 1e-6 + 1.2e-7 * (len(path) + 2)
            bound = self.kept.low.get(name, -np.inf) - slack - digits
            if wide and k <= PIECES:
                tops = s[: wide * PIECES].reshape(PIECES, wide).max(axis=1)
                tops.partition(PIECES - k)
                bound = max(bound, float(tops[PIECES - k]) / size - 2 * slack - digits)
            take = (s >= np.float32(bound * size - slack)).nonzero()[0]
            if len(take):
                u[0, places] = unit_counts
                exact = [(u * (counts[t].astype(np.float64) / norm[t])).sum(axis=1) for t in (take[i : i + READ] for i in range(0, len(take), READ))]
                u[0, places] = 0
                self.kept._merge(name, np.concatenate(exact), ids[take])


def knn_counts(queries: DataFrame, passages: DataFrame, text: str, key: str, k: int, dims: int) -> DataFrame:
    """(query_id, rank, id, score) of the k nearest ``passages`` for each of ``queries(query_id, code)``, by the cosine of hashed counts; exact, ties to the smaller id."""
    spark = passages.sparkSession
    size = queries.limit(ASKED * SLICES + 1).count()
    if not size or k < 1:
        return spark.createDataFrame([], "query_id long, rank int, id long, score double")
    if size > ASKED * SLICES:
        return knn_gemm(_vectors(queries, dims), hashed_vectors(passages, text, key, dims), k)

    def scan(held):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            paths = _Paths(*held.value, k, dims)
            ids, counts, n = np.empty(HELD, np.int64), np.empty((HELD, dims), np.float32), 0
            for batch in batches:
                at = 0
                while at < batch.num_rows:
                    part = batch.slice(at, min(READ, HELD - n))
                    ids[n : n + part.num_rows] = part.column("id").to_numpy()
                    counts[n : n + part.num_rows] = _counts(part.column("text").to_pylist(), dims)
                    n, at = n + part.num_rows, at + part.num_rows
                    if n == HELD:
                        paths.add(ids, counts)
                        n = 0
            if n:
                paths.add(ids[:n], counts[:n])
            yield from paths.kept.rows()

        return run

    sent, part = [], []
    for r in queries.select("query_id", "code").toLocalIterator():  # one slice at a time on the driver
        part.append((r.query_id, bytes(r.code)))
        if len(part) == ASKED:
            sent.append(part)
            part = []
    held = [spark.sparkContext.broadcast((np.array([i for i, _ in p], np.int64), [c for _, c in p])) for p in sent + [part] if p]
    told = passages.select(F.col(key).cast("long").alias("id"), F.col(text).cast("string").alias("text")).coalesce(2 * spark.sparkContext.defaultParallelism)  # a task that sees more keeps fewer rows
    return rank(reduce(lambda a, b: a.unionByName(b), [told.mapInArrow(scan(h), RANKED) for h in held]), k)


def _vectors(queries: DataFrame, dims: int) -> DataFrame:
    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = np.zeros((batch.num_rows, dims), np.float32)
            for row, code in zip(out, batch.column("code").to_pylist()):
                found = np.frombuffer(code, np.uint32).reshape(-1, 2)
                row[found[:, 0]] = found[:, 1]
            yield pa.RecordBatch.from_arrays([batch.column("query_id"), pa.array(list(out), pa.list_(pa.float32()))], ["query_id", "vector"])

    return queries.select("query_id", "code").mapInArrow(read, "query_id long, vector array<float>")
