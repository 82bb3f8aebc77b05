"""Training losses as DataFrame queries: pooled contrastive with gathered negatives, late interaction, and their mean.

``batch(rank, pos, query, document)``: pair ``pos`` of worker ``rank`` with both
vectors.  Candidates of a worker are its own documents, then those of the other
workers in order, cut at min(cap, all of them); late interaction stays local.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from litspark.functions.vectors import matrix, unit
from litspark.operators.index import QUERY_BYTES, maxsim_scores

TAU = 0.05
#: Rows of a block of queries and of a block of documents.
ASKED, ANSWERED = 512, 2048
BLOCK = "rank long, ids binary, vectors binary, n int"
PARTIAL = "rank long, pos long, top double, total double, own double"
Score = Callable[[np.ndarray, np.ndarray], np.ndarray]


def candidates(batch: DataFrame, gather: bool = True, cap: int | None = None) -> DataFrame:
    """(rank, c_rank, c_pos, document): what each worker scores its queries against."""
    docs = batch.select(F.col("rank").alias("c_rank"), F.col("pos").alias("c_pos"), "document")
    ranks = batch.groupBy("rank").agg(F.count("*").alias("local"))
    if not gather:
        return ranks.join(docs, F.col("rank") == F.col("c_rank")).select("rank", "c_rank", "c_pos", "document")
    every = docs.crossJoin(F.broadcast(ranks))  # a step's batch: workers x documents, bounded by the cap
    order = Window.partitionBy("rank").orderBy((F.col("c_rank") != F.col("rank")).cast("int"), "c_rank", "c_pos")
    placed = every.withColumn("n", F.row_number().over(order))
    return (placed.where(F.col("n") <= F.greatest(F.lit(cap), "local")) if cap is not None else placed).select("rank", "c_rank", "c_pos", "document")


def _blocks(batch: DataFrame, column: str, size: int) -> DataFrame:
    """The pairs' queries or documents as matrices of up to ``size`` rows of one rank."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}

        def out(rank: int, whole: bool) -> Iterator[pa.RecordBatch]:
            ids, v = (np.concatenate(x) for x in zip(*held[rank]))
            end = len(ids) if whole else len(ids) // size * size
            for at in range(0, end, size):
                a, b = ids[at : min(at + size, end)], v[at : min(at + size, end)]
                yield pa.RecordBatch.from_arrays([pa.array([rank], pa.int64()), pa.array([a.tobytes()]), pa.array([b.tobytes()]), pa.array([len(a)], pa.int32())], ["rank", "ids", "vectors", "n"])
            held[rank] = [(ids[end:], v[end:])]

        for batch in batches:
            widths = batch.column("v").value_lengths().drop_null().unique().to_pylist()
            if len(widths) > 1:
                raise ValueError("vectors of different sizes")
            if not widths:
                continue
            ranks, ids, v = batch.column("rank").to_numpy(), batch.column("pos").to_numpy(), matrix(batch.column("v"), widths[0])
            for rank in np.unique(ranks).tolist():
                held.setdefault(rank, []).append((ids[ranks == rank], v[ranks == rank]))
                if sum(len(x) for x, _ in held[rank]) >= size:
                    yield from out(rank, False)
        for rank in held:
            yield from out(rank, True)

    return batch.select(F.col("rank").cast("long"), F.col("pos").cast("long"), F.col(column).alias("v")).mapInArrow(pack, BLOCK)


def _read(row) -> tuple[int, np.ndarray, np.ndarray]:
    return row["rank"], np.frombuffer(row["ids"], np.int64), np.frombuffer(row["vectors"], np.float64).reshape(row["n"], -1)


def _cross_entropy(batch: DataFrame, score: Score, gather: bool, cap: int | None = None) -> DataFrame:
    """Mean over (rank, pos) of -log softmax at the pair's own document, per rank.

    Blocks of queries meet blocks of documents; each block leaves the largest
    score, the sum of exponentials beside it and the own score, so that what is
    shuffled grows with the pairs of the batch, not with their square.
    """
    spark = batch.sparkSession
    docs = _blocks(batch, "document", ANSWERED).persist()
    local = {r["rank"]: r for r in docs.groupBy("rank").agg(F.sum("n").alias("n"), F.sum(F.length("vectors")).alias("bytes")).collect()}  # the workers
    size = sum(r["n"] for r in local.values())
    cap = None if cap is not None and cap >= size else cap  # nobody's candidates are cut
    others = gather and (cap is None or any(r["n"] < cap for r in local.values()))
    first: list[tuple[int, np.ndarray, np.ndarray]] = []
    if others and cap is not None:
        # the others' first documents are among the first ``cap`` of all
        head = [(r["rank"], r["pos"], r["document"]) for r in batch.select("rank", "pos", "document").orderBy("rank", "pos").limit(cap).collect()]
        for rank in sorted({r for r, _, _ in head}):
            own = [(p, d) for r, p, d in head if r == rank]
            first.append((rank, np.array([p for p, _ in own], np.int64), np.array([d for _, d in own], np.float64)))
    counts, shared = {k: r["n"] for k, r in local.items()}, spark.sparkContext.broadcast(first)

    def meet(asked, answered) -> Iterator[tuple]:
        rank, ids, q = asked
        top, total, own = np.full(len(ids), -np.inf), np.zeros(len(ids)), np.full(len(ids), -np.inf)
        for c_rank, c_ids, d in answered:
            s = score(q, d)
            if c_rank == rank:
                own = np.maximum(own, np.where(ids[:, None] == c_ids[None], s, -np.inf).max(axis=1))
            new = np.maximum(top, s.max(axis=1))
            total = total * np.exp(top - new) + np.exp(s - new[:, None]).sum(axis=1)
            top = new
        return zip([rank] * len(ids), ids.tolist(), top.tolist(), total.tolist(), [x if x > -np.inf else None for x in own.tolist()])

    def heads(rank: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        left = cap - counts[rank]
        for c_rank, ids, d in shared.value:
            if c_rank != rank and left > 0:
                yield c_rank, ids[:left], d[:left]
                left -= len(ids)

    def emit(rows: list[tuple]) -> pa.RecordBatch:
        kinds = (pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64())
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], ["rank", "pos", "top", "total", "own"])

    every = others and cap is None
    tasks = max(spark.sparkContext.defaultParallelism, -(-size // (8 * ASKED)))
    asked = _blocks(batch.select("rank", "pos", "query").repartition(tasks), "query", ASKED)
    if sum(r["bytes"] for r in local.values()) <= QUERY_BYTES:
        held = spark.sparkContext.broadcast([(r["rank"], bytes(r["ids"]), bytes(r["vectors"]), r["n"]) for r in docs.collect()])  # at most QUERY_BYTES

        def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            answers = [_read(dict(zip(("rank", "ids", "vectors", "n"), x))) for x in held.value]
            for batch in batches:
                for row in batch.to_pylist():
                    one = _read(row)
                    mine = [a for a in answers if every or a[0] == one[0]] + (list(heads(one[0])) if others and not every else [])
                    yield emit(list(meet(one, mine)))

        parts = asked.mapInArrow(scan, PARTIAL)
    else:
        right = docs.select(*[F.col(c).alias(f"c_{c}") for c in docs.columns])

        def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for i in range(batch.num_rows):
                    row = batch.slice(i, 1).to_pylist()[0]
                    yield emit(list(meet(_read(row), [_read({c: row[f"c_{c}"] for c in ("rank", "ids", "vectors", "n")})])))

        def beside(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row in batch.to_pylist():
                    one = _read(row)
                    if found := list(heads(one[0])):
                        yield emit(list(meet(one, found)))

        met = asked.crossJoin(right) if every else asked.join(right, F.col("rank") == F.col("c_rank"))
        parts = met.mapInArrow(pairs, PARTIAL)
        parts = parts.unionByName(asked.mapInArrow(beside, PARTIAL)) if others and not every else parts
    listed = parts.groupBy("rank", "pos").agg(F.max("top").alias("m"), F.collect_list(F.struct("top", "total")).alias("x"), F.max("own").alias("own"))
    total = F.aggregate("x", F.lit(0.0), lambda a, x: a + x["total"] * F.exp(x["top"] - F.col("m")))
    each = listed.select(F.col("rank").cast(batch.schema["rank"].dataType).alias("rank"), (F.log(total) + F.col("m") - F.col("own")).alias("loss"))
    return each.groupBy("rank").agg(F.avg("loss").alias("loss"), F.count("*").alias("pairs"))


def contrastive(batch: DataFrame, gather: bool = True, cap: int | None = None, tau: float = TAU) -> DataFrame:
    """(rank, loss, pairs): softmax over pooled cosines / tau."""
    return _cross_entropy(batch, lambda q, d: unit(q) @ unit(d).T / tau, gather, cap)


def late_interaction(batch: DataFrame, width: int, tau: float = TAU) -> DataFrame:
    """(rank, loss, pairs): softmax over local MaxSim / (query tokens * tau)."""
    return _cross_entropy(batch, lambda q, d: maxsim_scores(q, d, width) / (q.shape[1] // width * tau), False)


def hybrid(batch: DataFrame, width: int, gather: bool = True, cap: int | None = None, tau: float = TAU) -> DataFrame:
    """(rank, contrastive, late, loss): the loss is the mean of both."""
    a, b = contrastive(batch, gather, cap, tau), late_interaction(batch, width, tau)
    return a.select("rank", F.col("loss").alias("contrastive")).join(b.select("rank", F.col("loss").alias("late")), "rank").withColumn("loss", (F.col("contrastive") + F.col("late")) / 2)
