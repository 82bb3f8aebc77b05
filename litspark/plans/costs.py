"""Counted costs: operations of each stage, rates, scaling curves, normalised comparisons and projections."""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from litspark.functions.text import token_array

# The published rates (samples a second), workers and total samples that projections refer to.
PUBLISHED = [
    ("parse two-stage", "system A", 1024, 118.2), ("parse end-to-end", "system A", 1024, 38.9), ("parse end-to-end", "system B", 1152, 35.62),
    ("chunk", "system A", 1024, 385.7), ("chunk", "system B", 1152, 319.8), ("train quantised", "system A", 1600, 3496.4),
]
NODES = {("parse two-stage", "system A"): 256, ("parse end-to-end", "system A"): 256, ("parse end-to-end", "system B"): 96, ("chunk", "system A"): 256, ("chunk", "system B"): 96, ("train quantised", "system A"): 400}

#: What a stage takes as a sample.
SAMPLES = {"parse": "page", "chunk": "document", "train": "question"}
#: Size classes of texts: 8 tokens times a power of 4.
SIZE_CLASSES = 12


def flops(stage: str, *, queries: int = 0, chunks: int = 0, dims: int = 0, query_tokens: int = 0, chunk_tokens: int = 0, tokens: int = 0, rank: int = 0, candidates: int = 0) -> float:
    """Analytic operation counts (not measured)."""
    if stage == "pooled":
        return 2.0 * queries * chunks * dims
    if stage == "maxsim":
        return 2.0 * queries * query_tokens * chunks * chunk_tokens * dims
    if stage == "encode":
        return 2.0 * tokens * dims * (1 + 2 * rank)
    if stage == "train":
        return 3 * flops("encode", tokens=tokens, dims=dims, rank=rank) + 2.0 * queries * candidates * dims
    if stage == "gather":
        return 4.0 * candidates * dims
    raise ValueError(stage)


def pair_ops(query_tokens: int, chunk_tokens: int, metric: str) -> int:
    return query_tokens * chunk_tokens if metric == "maxsim" else 1


def epoch_hours(samples: float, rate: float) -> float:
    return samples / rate / 3600


def flop_model(docs: DataFrame) -> DataFrame:
    """Pooled against token-level cost of one question of 8 tokens with every text as texts grow: (tokens, texts, pooled, maxsim, ratio).

    ``tokens`` is the bound of a size class, 8 times a power of 4.
    """
    size = F.size(token_array(F.coalesce("text", F.lit(""))))
    bound = reduce(lambda rest, t: F.when(F.col("n") <= t, t).otherwise(rest), [8 * 4**k for k in range(SIZE_CLASSES - 1, -1, -1)], F.lit(2**31 - 1))
    grown = docs.select(size.alias("n")).groupBy(bound.alias("tokens")).agg(F.count("*").alias("texts"), F.sum(F.col("n").cast("long")).alias("n"))
    pooled, maxsim = flops("pooled", queries=1, chunks=1, dims=64), flops("maxsim", queries=1, chunks=1, dims=64, query_tokens=8, chunk_tokens=1)
    return grown.select("tokens", "texts", (F.col("texts") * pooled).alias("pooled"), (F.col("n") * maxsim).alias("maxsim")).withColumn("ratio", F.col("maxsim") / F.col("pooled"))


def normalised(spark: SparkSession, samples: DataFrame) -> DataFrame:
    """Published rates per accelerator and per node, and hours for ``samples(kind, samples)`` at each rate."""
    rows = [(s, m, w, r, round(r / w, 6), round(r / NODES[s, m], 6), SAMPLES[s.split()[0]]) for s, m, w, r in PUBLISHED]
    rated = spark.createDataFrame(rows, "stage string, machine string, workers int, rate double, per_worker double, per_node double, kind string")
    return rated.join(samples, "kind").select("stage", "machine", "workers", "rate", "per_worker", "per_node", "samples", F.round(F.col("samples") / F.col("rate") / 3600, 4).alias("epoch_hours"))


def timed(run: Callable[[], DataFrame]) -> float:
    """Seconds to compute all rows of a plan, without writing them."""
    began = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def scaling_curve(spark: SparkSession, run: Callable[[DataFrame], DataFrame], table: DataFrame, workers: tuple[int, ...] = (1, 2, 4)) -> DataFrame:
    """Strong scaling inside one session: the same rows over p partitions; (workers, seconds, rows a second, efficiency)."""
    held = table.persist()
    n = held.count()
    run(held.limit(100)).write.format("noop").mode("overwrite").save()  # warm up
    rows, base = [], None
    for p in workers:
        seconds = timed(lambda p=p: run(held.repartition(p)))
        rate = n / seconds
        base = base or rate / p
        rows.append((p, seconds, rate, rate / (p * base)))
    held.unpersist()
    return spark.createDataFrame(rows, "workers int, seconds double, rows_per_s double, efficiency double")


def throughput(spark: SparkSession, runs: dict[str, Callable[[], DataFrame]], rows: int, cores: int) -> DataFrame:
    """(name, seconds, rows a second, rows a core-second) of each plan over the same rows."""
    out = []
    for name, run in runs.items():
        seconds = timed(run)
        out.append((name, seconds, rows / seconds, rows / seconds / cores))
    return spark.createDataFrame(out, "name string, seconds double, rows_per_s double, rows_per_core_s double")


def training_rates(log: list[dict], workers: int, dims: int, rank: int, batch: int) -> dict[str, float]:
    """Rates of a run's log: samples and steps a second, all samples, counted operations, and operations a second and worker.

    Operations are counted from the tokens that the run read, not measured.  The
    first step, which warms up, is left out of the rates where there are others.
    """
    timed = log[1:] or log
    seconds = sum(r["seconds"] for r in timed)
    count = lambda rows: sum(flops("train", tokens=r["tokens"], dims=dims, rank=rank, queries=r["pairs"], candidates=r["candidates"]) for r in rows)
    return {
        "steps": len(log), "samples": sum(r["pairs"] for r in log), "samples_per_s": sum(r["pairs"] for r in timed) / seconds, "steps_per_s": len(timed) / seconds,
        "flops": count(log), "tflops_per_worker": flops_per_worker(count(timed), seconds, workers) / 1e12, "sent_mb": sum(r["sent"] for r in log) / 1e6, "load_seconds": max(r["load_seconds"] for r in log),
        "projected_epoch_hours": epoch_hours(16.4e6, sum(r["pairs"] for r in timed) / seconds),
    }


def flops_per_worker(operations: float, seconds: float, workers: int) -> float:
    return operations / (seconds * workers)
