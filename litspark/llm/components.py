"""Connected components: one task for a bounded number of links, repeated contraction of tables beyond it."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from litspark.llm.common import Scratch


#: Links that one task may join by itself; it holds two short keys for each.
LOCAL_LINKS = 250_000


def connected_components(edges: DataFrame, scratch: Scratch, local: int = LOCAL_LINKS) -> DataFrame:
    """(node, component) for every node of ``edges(a, b)``, binary keys; the component is its smallest node.

    ``edges`` is held: it is counted first.  At most ``local`` links are joined by
    one task with a union-find; more by ``contracted``.  Self loops and repeated
    edges are harmless; null ends are dropped.
    """
    known = edges.where("a is not null and b is not null and a <> b").select("a", "b")
    if known.count() > local:
        return contracted(known, scratch)
    return scratch.write(known.coalesce(1).mapInArrow(_joined, "node binary, component binary"))


def _joined(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    above: dict[bytes, bytes] = {}

    def root(x: bytes) -> bytes:
        while above[x] != x:
            above[x] = x = above[above[x]]
        return x

    for batch in rows:
        for a, b in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist()):
            above.setdefault(a, a)
            above.setdefault(b, b)
            low, high = sorted((root(a), root(b)))
            above[high] = low
    nodes = list(above)
    yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.binary()), pa.array(map(root, nodes), pa.binary())], ["node", "component"])


def contracted(edges: DataFrame, scratch: Scratch) -> DataFrame:
    """Components by contraction; all state stays in tables.

    Each round every node hooks to its smallest neighbour (or itself), pointers
    are followed to their roots, and the edges are rewritten between roots; a
    round at least halves the nodes that still have edges.  Self loops and
    repeated edges are harmless; null ends are dropped.
    """
    live = scratch.write(edges.where("a is not null and b is not null and a <> b").select("a", "b").distinct(), "edges")
    labels = scratch.write(
        live.select(F.explode(F.array("a", "b")).alias("node")).distinct().select("node", F.col("node").alias("component")), "labels"
    )
    while not live.isEmpty():
        both = live.unionByName(live.select(F.col("b").alias("a"), F.col("a").alias("b")))
        hooks = both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("low")).select("node", F.least("node", "low").alias("root"))
        hooks = scratch.write(hooks, "hooks")
        while True:
            up = hooks.select(F.col("node").alias("root"), F.col("root").alias("above"))
            jumped = scratch.write(hooks.join(up, "root").select("node", F.col("above").alias("root"), (F.col("above") != F.col("root")).alias("moved")), "jump")
            moved = not jumped.where("moved").isEmpty()
            scratch.drop(hooks)
            hooks = jumped
            if not moved:
                break
        of = hooks.select(F.col("node").alias("component"), "root")
        fresh = scratch.write(labels.join(of, "component", "left").select("node", F.coalesce("root", "component").alias("component")), "labels")
        ends = hooks.select(F.col("node").alias("a"), F.col("root").alias("ra")), hooks.select(F.col("node").alias("b"), F.col("root").alias("rb"))
        left = scratch.write(
            live.join(ends[0], "a").join(ends[1], "b").where("ra <> rb").select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct(),
            "edges",
        )
        scratch.drop(labels, live, hooks)
        labels, live = fresh, left
    return labels
