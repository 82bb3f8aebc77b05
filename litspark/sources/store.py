"""The vector store: vectors by cell and passages by id, written once and read late."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from litspark.operators.index import build_ivf


def write_index(path: str, vectors: DataFrame, passages: DataFrame, seeds: DataFrame, version: str) -> None:
    """``vectors(id, vector)`` under ``path/vectors`` partitioned by cell, ``passages(id, text)`` under ``path/passages``, seeds beside them."""
    seeds.write.mode("overwrite").parquet(f"{path}/seeds")
    build_ivf(vectors, seeds).withColumn("version", F.lit(version)).write.mode("overwrite").partitionBy("cell").parquet(f"{path}/vectors")
    passages.select("id", "text").write.mode("overwrite").parquet(f"{path}/passages")


def read_index(spark: SparkSession, path: str, version: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(vectors, passages, seeds); vectors of another encoder version are an error."""
    vectors = spark.read.parquet(f"{path}/vectors")
    if not vectors.where(F.col("version") != version).isEmpty():
        raise ValueError("the index was built by another encoder version")
    return vectors.drop("version"), spark.read.parquet(f"{path}/passages"), spark.read.parquet(f"{path}/seeds")


def fetch_passages(hits: DataFrame, passages: DataFrame) -> DataFrame:
    """Texts of the winners only: hits are queries x k rows, the passages are scanned by id."""
    return passages.join(hits, "id")


def run_stage(name: str, df: DataFrame, stage, rows_per_task: int = 50_000, path: str | None = None) -> tuple[DataFrame, dict]:
    """A farm of independent tasks: ``stage(df)`` over about ``rows_per_task`` rows a task, and what the run took.

    The rows are dealt evenly, so one large file or partition does not hold a task
    up; with ``path`` the result is written there and read back, so that a lost
    executor costs its running tasks only.  The report has name, rows, tasks and
    seconds (of the write, None without one).
    """
    import time
    from math import ceil

    rows = df.count()
    tasks = max(1, ceil(rows / rows_per_task))
    made = stage(df.repartition(tasks))
    seconds = None
    if path:
        began = time.perf_counter()
        made.write.mode("overwrite").parquet(path)
        seconds = time.perf_counter() - began
        made = df.sparkSession.read.schema(made.schema).parquet(path)
    return made, {"name": name, "rows": rows, "tasks": tasks, "seconds": seconds}
