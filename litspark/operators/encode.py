"""Text encoders: hashed counts, and a frozen hashed token table with a trainable adapter.

The table stands in for the layers of a large language model: every token maps
to one of ``BUCKETS`` Gaussian rows, small (64 dimensions) or large (256).  The
adapter is low-rank (e + eAB) or a scaling by element (e * s); a quantised base
keeps its rows as 8-bit codes.  A token's vector is the average with its
neighbours, a text's vector the normalised mean of its tokens'.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from litspark.functions.text import split_tokens, token_code, token_codes
from litspark.functions.vectors import unit
from litspark.operators.chunk import chunk_words
from litspark.operators.index import quantise
from litspark.operators.registry import REGISTRY

BUCKETS = 2**14
SIZES = {"small": 64, "large": 256}
RANK = 8
SEED = 42
#: Texts that are summed at a time.
MEANS = 256


def base_table(size: str, quantised: bool = False, seed: int = SEED) -> np.ndarray:
    """The frozen rows, as floats; the quantised base has passed through 8-bit codes."""
    table = np.random.default_rng(seed).standard_normal((BUCKETS, SIZES[size])).astype(np.float32)
    if quantised:
        codes, scale = quantise(table)
        table = (codes.astype(np.float32) * scale[:, None]).astype(np.float32)
    return table


@dataclass
class Adapter:
    """What is trained. kind: lora, ia3 or none."""

    kind: str
    weights: dict[str, np.ndarray] = field(default_factory=dict)

    @classmethod
    def start(cls, kind: str, dims: int, rank: int = RANK, seed: int = SEED) -> "Adapter":
        """An adapter that changes nothing yet."""
        if kind == "lora":
            return cls(kind, {"A": np.random.default_rng(seed).standard_normal((dims, rank)) / np.sqrt(dims), "B": np.zeros((rank, dims))})
        return cls(kind, {"s": np.ones(dims)} if kind == "ia3" else {})

    def apply(self, rows: np.ndarray) -> np.ndarray:
        if self.kind == "lora":
            return rows + rows @ self.weights["A"] @ self.weights["B"]
        return rows * self.weights["s"] if self.kind == "ia3" else rows

    def backward(self, rows: np.ndarray, grad: np.ndarray) -> dict[str, np.ndarray]:
        """Gradients of the weights from the gradient of ``apply(rows)``."""
        if self.kind == "lora":
            a, b = self.weights["A"], self.weights["B"]
            return {"A": rows.T @ (grad @ b.T), "B": (rows @ a).T @ grad}
        return {"s": (rows * grad).sum(axis=0)} if self.kind == "ia3" else {}


@dataclass(frozen=True)
class EncoderSpec:
    size: str = "small"
    quantised: bool = False


def token_rows(table: np.ndarray, text: str, idf: dict[str, float] | None = None) -> np.ndarray:
    """Context averages of the frozen rows of a text's tokens (before the adapter, which is linear)."""
    words = split_tokens(text or "")
    if not words:
        return np.zeros((0, table.shape[1]))
    rows = table[[token_code(w) % BUCKETS for w in words]].astype(np.float64)
    if idf is not None:
        rows *= np.array([idf.get(w, 1.0) for w in words])[:, None]
    padded = np.zeros((len(rows) + 2, rows.shape[1]))
    padded[1:-1] = rows
    counts = np.full(len(rows), 3.0)
    counts[0] -= 1
    counts[-1] -= 1
    return (padded[:-2] + padded[1:-1] + padded[2:]) / counts[:, None]


def token_means(table: np.ndarray, words: list[str], sizes: np.ndarray, idf: dict[str, float] | None = None) -> np.ndarray:
    """The mean of ``token_rows`` of each text, from the tokens of all texts in one list and how many each has.

    A token's row counts in its own context average and in those beside it, so the
    mean is a weighted sum of rows; texts of like length are summed place by place.
    """
    out = np.zeros((len(sizes), table.shape[1]))
    if not len(words):
        return out
    ends = np.cumsum(sizes)
    firsts, lasts = (ends - sizes)[sizes > 0], ends[sizes > 0] - 1
    around = np.full(len(words), 3.0)
    np.subtract.at(around, firsts, 1)
    np.subtract.at(around, lasts, 1)
    share = 1 / around
    left, right = np.append(0, share[:-1]), np.append(share[1:], 0)
    left[firsts] = right[lasts] = 0
    weight = share + left + right
    if idf is not None:
        weight *= np.array([idf.get(w, 1.0) for w in words])
    codes = np.array(token_codes(words), np.int64) % BUCKETS
    order = np.argsort(-sizes, kind="stable")
    for at in range(0, len(order), MEANS):
        who = order[at : at + MEANS]
        n, start = sizes[who], (ends - sizes)[who]
        some = np.zeros((len(who), table.shape[1]))
        for place in range(int(n[0])):
            here = start[: np.searchsorted(-n, -place, side="left")] + place
            some[: len(here)] += table[codes[here]] * weight[here, None]
        out[who] = some / np.maximum(n, 1)[:, None]
    return out


class Bank:
    """Several encoders, each a (spec, adapter, idf), that read a text once; equal bases are summed once."""

    def __init__(self, states: list[tuple]):
        self.states = [(spec, adapter or Adapter("none"), idf) for spec, adapter, idf in states]
        self.tables = {spec: base_table(spec.size, spec.quantised).astype(np.float64) for spec, _, _ in self.states}

    def vectors(self, words: list[str], sizes: np.ndarray) -> list[np.ndarray]:
        """Pooled unit vectors in 32 bits of each encoder."""
        means: dict[tuple, np.ndarray] = {}
        out = []
        for spec, adapter, idf in self.states:
            key = spec, id(idf)
            if key not in means:
                means[key] = token_means(self.tables[spec], words, sizes, idf)
            out.append(unit(adapter.apply(means[key])).astype(np.float32))
        return out

    def texts(self, texts: list[str | None]) -> list[np.ndarray]:
        words = [split_tokens(t or "") for t in texts]
        return self.vectors(list(chain.from_iterable(words)), np.array([len(w) for w in words], np.int64))

    def chunks(self, batch: pa.RecordBatch) -> Iterator[tuple[np.ndarray, list[np.ndarray]]]:
        """(ids, vectors of each encoder) of the chunks of a batch of documents."""
        for ids, words, sizes in chunk_words(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()):
            yield ids, self.vectors(words, sizes)


def _bank(states: bytes) -> Bank:
    return Bank(pickle.loads(states))


def worker_bank(states: list[tuple]) -> Bank:
    """The encoders of this worker process."""
    return REGISTRY.get(_bank, pickle.dumps(states))


class Encoder:
    """Encodes texts; a spec, an adapter and, if fitted, token weights."""

    def __init__(self, spec: EncoderSpec, adapter: Adapter | None = None, idf: dict[str, float] | None = None):
        self.spec, self.adapter, self.idf = spec, adapter or Adapter("none"), idf
        self.table = base_table(spec.size, spec.quantised)

    def tokens(self, text: str) -> np.ndarray:
        return self.adapter.apply(token_rows(self.table, text, self.idf))

    def pooled(self, texts: list[str]) -> np.ndarray:
        words = [split_tokens(t or "") for t in texts]
        return unit(self.adapter.apply(token_means(self.table, list(chain.from_iterable(words)), np.array([len(w) for w in words], np.int64), self.idf)))


def with_pooled(df: DataFrame, text: str, key: str, spec: EncoderSpec, adapter: Adapter | None = None, warm: bool = True, idf: dict[str, float] | None = None) -> DataFrame:
    """(key, vector) of each text; the encoder lives in the worker's registry (or is built for each task when cold)."""
    held = df.sparkSession.sparkContext.broadcast((spec, adapter, idf))

    def encode(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = worker_encoder(held.value, warm)
        for batch in rows:
            vectors = encoder.pooled([t or "" for t in batch.column("text").to_pylist()]).astype(np.float32)
            flat = pa.array(vectors.ravel(), pa.float32())
            ends = pa.array(np.arange(len(vectors) + 1, dtype=np.int32) * (vectors.shape[1] if vectors.ndim == 2 else 0))
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.ListArray.from_arrays(ends, flat)], ["id", "vector"])

    return df.select(F.col(key).cast("long").alias("id"), F.col(text).cast("string").alias("text")).mapInArrow(encode, "id long, vector array<float>")


def _encoder(state: bytes) -> Encoder:
    return Encoder(*pickle.loads(state))


def worker_encoder(state: tuple, warm: bool = True) -> Encoder:
    """The encoder of this worker process.

    A function of the module, so that tasks reach the registry of their process:
    one named inside a shipped closure would be copied into every task.
    """
    if not warm:
        REGISTRY.drop()
    return REGISTRY.get(_encoder, pickle.dumps(state))


def worker_trace() -> tuple[int, int, int, float]:
    return REGISTRY.trace()


def registry_trace(df: DataFrame, spec: EncoderSpec, warm: bool = True) -> DataFrame:
    """One row per task: process, loads and hits so far in it, seconds spent loading."""

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = 0
        encoder = worker_encoder((spec, None, None), warm)
        for batch in rows:
            n += len(encoder.pooled([t or "" for t in batch.column("text").to_pylist()]))
        pid, loads, hits, seconds = worker_trace()
        yield pa.RecordBatch.from_arrays([pa.array([x]) for x in (pid, loads, hits, seconds, n)], ["process", "loads", "hits", "load_seconds", "texts"])

    return df.select(F.col("text").cast("string").alias("text")).mapInArrow(run, "process long, loads long, hits long, load_seconds double, texts long")


def chunk_pooled(docs: DataFrame, state: tuple) -> DataFrame:
    """(id, vector) of ``with_pooled`` for the semantic chunks of ``docs(doc_id, text)``, an id as in ``chunk_words``; no text is written or read again."""
    held = docs.sparkSession.sparkContext.broadcast([state])

    def encode(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bank = worker_bank(held.value)
        for batch in rows:
            for ids, (vectors,) in bank.chunks(batch):
                ends = pa.array(np.arange(len(ids) + 1, dtype=np.int32) * vectors.shape[1])
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.ListArray.from_arrays(ends, pa.array(vectors.ravel(), pa.float32()))], ["id", "vector"])

    return docs.select("doc_id", "text").mapInArrow(encode, "id long, vector array<float>")


def hashed_vectors(df: DataFrame, text: str, key: str, dims: int = 64) -> DataFrame:
    """(id, vector) of exact hashed counts; no shuffle."""

    def encode(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            out = np.zeros((batch.num_rows, dims), np.float32)
            for i, t in enumerate(batch.column("text").to_pylist()):
                np.add.at(out[i], [token_code(w) % dims for w in split_tokens(t or "")], 1)
            ends = pa.array(np.arange(len(out) + 1, dtype=np.int32) * dims)
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.ListArray.from_arrays(ends, pa.array(out.ravel(), pa.float32()))], ["id", "vector"])

    return df.select(F.col(key).cast("long").alias("id"), F.col(text).cast("string").alias("text")).mapInArrow(encode, "id long, vector array<float>")


def fit_idf(docs: DataFrame, least: int = 2, limit: int = 200_000) -> dict[str, float]:
    """Token weights from a corpus, for the domain encoder: the ``limit`` most frequent tokens of at least ``least`` documents."""
    from litspark.operators.pairs import document_frequency

    n = docs.count()
    rows = document_frequency(docs).where(F.col("df") >= least).orderBy(F.desc("df"), "token").limit(limit).toLocalIterator()
    return {r.token: float(np.log((1 + n) / (1 + r.df))) for r in rows}
