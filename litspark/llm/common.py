"""Shared plumbing of the training-data operators: scratch tables, bounded broadcasts, text columns."""

from __future__ import annotations

import atexit
import contextlib
import contextvars
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of a side that may be broadcast; a row here is a few longs or short keys, so about 20 MB.
BROADCAST_ROWS = 200_000

_made: contextvars.ContextVar[list["Scratch"] | None] = contextvars.ContextVar("made", default=None)


def shared_folder(spark: SparkSession) -> str:
    """The folder named in ``spark.checkpoint.dir``.

    Where it is unset: a temporary folder if the driver and the executors are one
    process, else a folder in the warehouse, which a cluster shares.
    """
    context = spark.sparkContext
    named = context.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not context.master.startswith("local[") and context.master != "local":
        return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/litspark"
    own = getattr(shared_folder, "own", None)
    if own is None:
        own = shared_folder.own = tempfile.mkdtemp(prefix="litspark-")
    return own


class Scratch:
    """Written tables that cut lineage; they sit in the shared folder and go when closed, dropped, or when the process ends.

    A result of an operator reads the tables of the operator's own scratch, so it
    is good until that scratch is closed; no other call touches it.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{shared_folder(spark)}/scratch/{name}-{uuid.uuid4().hex}"
        self.count = 0
        self.paths: dict[int, str] = {}
        if (made := _made.get()) is not None:
            made.append(self)
        atexit.register(_remove, spark, self.root)

    def write(self, df: DataFrame, label: str = "t") -> DataFrame:
        """The same rows, read back from a table of their own."""
        self.count += 1
        path = f"{self.root}/{self.count}-{label}"
        df.write.option("compression", "zstd").parquet(path)
        back = self.spark.read.schema(df.schema).parquet(path)
        self.paths[id(back)] = path
        return back

    def drop(self, *tables: DataFrame) -> None:
        """Delete tables that no later plan reads."""
        for t in tables:
            path = self.paths.pop(id(t), None)
            if path:
                _remove(self.spark, path)

    def close(self) -> None:
        _remove(self.spark, self.root)
        self.paths.clear()


@contextlib.contextmanager
def scratches() -> Iterator[list[Scratch]]:
    """The scratches that are opened inside, for whoever writes the results elsewhere to close afterwards."""
    made: list[Scratch] = []
    token = _made.set(made)
    try:
        yield made
    finally:
        _made.reset(token)


def fresh(df: DataFrame, *names: str) -> list[str]:
    """The names, lengthened until no column of ``df`` has them in any case."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def drop_rows(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """``docs`` without the rows named by ``gone(doc_id, tag)``, tag being the hash of the text; nulls are values."""
    pick = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**63)))
    a, b = fresh(docs, "pick", "tag")
    named = gone.select(pick.alias(a), F.col("tag").alias(b)).distinct()
    marked = docs.withColumns({a: pick, b: F.xxhash64(F.col("text").cast("string"))})
    return marked.join(small(named), [a, b], "left_anti").drop(a, b)


def _remove(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark._jvm
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # the session may be gone at exit; the folder is scratch
        pass


def small(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``limit`` rows, else as it is (a shuffle join follows)."""
    return F.broadcast(df) if df.limit(limit + 1).count() <= limit else df


#: Rows of one key from which it counts as hot.
HOT_ROWS = 1000


def join_split(rows: DataFrame, one: DataFrame, key: str, count: str) -> DataFrame:
    """``rows`` joined with ``one``, which has one row a key and how many ``rows`` the key has, so that no hot key meets in one task.

    Hot keys are few (at most one in ``HOT_ROWS`` rows), so their side is broadcast
    while it is counted small; the other keys, or all beyond that, meet by a
    shuffle that may be split at run time.
    """
    hot = one.where(F.col(count) >= HOT_ROWS)
    found = hot.limit(BROADCAST_ROWS + 1).count()
    if not found:
        return rows.join(small(one), key)
    if found > BROADCAST_ROWS:
        return rows.join(one, key)
    names = F.broadcast(hot.select(key))
    return rows.join(F.broadcast(hot), key).unionByName(rows.join(names, key, "left_anti").join(one.where(F.col(count) < HOT_ROWS), key))


#: Rows of texts or pages in one Arrow batch between the JVM and a Python worker.
TEXT_ROWS = 1000


def text_batches(spark: SparkSession, rows: int = TEXT_ROWS) -> None:
    """Bound Arrow batches for wide rows: both sides hold a batch, and its buffers double while they grow.

    This is a runtime setting of the session; it is only ever lowered.
    """
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(key))
    if now <= 0 or now > rows:
        spark.conf.set(key, rows)


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")
