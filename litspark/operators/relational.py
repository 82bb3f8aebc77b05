"""Relational operators that the methods stand on and Spark lacks or needs care with: as-of, range and near-duplicate joins."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from litspark.functions.text import let, token_array
from litspark.operators.index import seldom

#: Shingles known as frequent: how many at most, and in how many texts of one partition.
FREQUENT, LOCAL = 100_000, 8
#: Pairs of ids that may be broadcast.
MEETINGS = 1_000_000


def asof_join(left: DataFrame, right: DataFrame, key: str, time: str, values: list[str], id_column: str) -> DataFrame:
    """``left`` with the values of the latest earlier (or equal) row of ``right`` with the same key.

    One sort by key and time over the union; ties in time go to the largest id.
    """
    a = left.select("*", F.lit(1).alias("_side"), *[F.lit(None).cast(right.schema[v].dataType).alias(f"_{v}") for v in values], F.lit(None).cast("long").alias("_id"))
    b = right.select(key, time, F.lit(0).alias("_side"), *[F.col(v).alias(f"_{v}") for v in values], F.col(id_column).alias("_id"))
    order = Window.partitionBy(key).orderBy(time, "_side", F.col("_id").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True)
    filled = both.select(*a.columns, *[F.last(f"_{v}", ignorenulls=True).over(order).alias(f"asof_{v}") for v in values])
    return filled.where("_side = 1").drop("_side", "_id", *[f"_{v}" for v in values])


def range_join(points: DataFrame, spans: DataFrame, point: str, low: str, high: str, width: int) -> DataFrame:
    """Points inside [low, high) of spans: an equi-join on buckets of ``width`` and a residual predicate, no nested loop."""
    p = points.withColumn("_b", F.floor(F.col(point) / width))
    s = spans.withColumn("_b", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor((F.col(high) - 1) / width))))
    return p.join(s, "_b").where((F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))).drop("_b")


def exact_duplicates(docs: DataFrame) -> DataFrame:
    """(cluster_id, copies): groups of equal texts, white space squeezed."""
    named = docs.select("doc_id", F.md5(F.trim(F.regexp_replace(F.coalesce("text", F.lit("")), r"\s+", " "))).alias("digest"))
    return named.groupBy("digest").agg(F.min("doc_id").alias("cluster_id"), F.count("*").alias("copies")).where("copies > 1").select("cluster_id", "copies")


#: Odd factors of the words of a shingle, by place.
_PLACES = np.array([int(hashlib.md5(str(i).encode()).hexdigest()[:16], 16) | 1 for i in range(64)], np.uint64)


def _shingles(docs: DataFrame, width: int) -> DataFrame:
    """(doc_id, g): 64-bit hashes of the distinct token shingles of each text that has any, in order of the hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            codes, ends = batch.column("w").flatten().to_numpy().view(np.uint64), np.cumsum(batch.column("w").value_lengths().to_numpy())
            out = []
            for at, end in zip([0, *ends[:-1]], ends):
                w = codes[at:end]
                h = sum(w[i : len(w) - width + 1 + i] * _PLACES[i] for i in range(width))
                h ^= h >> np.uint64(32)
                h *= _PLACES[-1]
                h ^= h >> np.uint64(29)
                out.append(np.unique(h.view(np.int64)))
            flat = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, out)]), pa.int32()), pa.array(np.concatenate(out) if out else [], pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), flat], ["doc_id", "g"])

    words = docs.where("doc_id is not null").select("doc_id", F.transform(token_array(F.coalesce("text", F.lit(""))), lambda t: F.xxhash64(t)).alias("w"))
    return words.where(F.size("w") >= width).mapInArrow(run, "doc_id long, g array<long>")


def _often(grams: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that stand in many texts, sorted, and about how many: those that a partition holds ``LOCAL`` times, at most ``FREQUENT``."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b.column("g").flatten().to_numpy() for b in batches]
        gram, n = np.unique(np.concatenate(held) if held else np.empty(0, np.int64), return_counts=True)
        yield pa.RecordBatch.from_arrays([pa.array(gram[n >= LOCAL]), pa.array(n[n >= LOCAL])], ["gram", "n"])

    top = grams.select("g").mapInArrow(count, "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "gram").limit(FREQUENT).toArrow()
    gram, n = top.column("gram").to_numpy(), top.column("n").to_numpy()
    order = np.argsort(gram)
    return gram[order], n[order]


def _heads(grams: DataFrame, percent: int) -> DataFrame:
    """(doc_id, n, same, head): size and digest of each set, and its first n - ceil(t n) + 1 shingles, those known as frequent last."""
    held = grams.sparkSession.sparkContext.broadcast(_often(grams))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, often = held.value
        for batch in batches:
            same, head = [], []
            sizes = batch.column("g").value_lengths().to_numpy()
            for g in np.split(batch.column("g").flatten().to_numpy(), np.cumsum(sizes)[:-1]) if len(sizes) else ():
                at = np.minimum(np.searchsorted(known, g), max(len(known) - 1, 0))
                rank = np.where(known[at] == g, often[at], 0) if len(known) else np.zeros(len(g), np.int64)
                same.append(hashlib.blake2b(g.tobytes(), digest_size=16).digest())
                head.append(g[np.lexsort((g, rank))[: len(g) + percent * len(g) // -100 + 1]])
            flat = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, head)]), pa.int32()), pa.array(np.concatenate(head) if head else [], pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(sizes, pa.int32()), pa.array(same, pa.binary()), flat], ["doc_id", "n", "same", "head"])

    return grams.mapInArrow(cut, "doc_id long, n int, same binary, head array<long>")


def near_pairs(docs: DataFrame, width: int = 5, percent: int = 75) -> DataFrame:
    """(a, b, shared, either): exact resemblance join of token shingles through prefixes of rare shingles.

    Equal sets are one class, and classes are compared.  Shingles are ordered by
    hash, the frequent ones last; two sets at the threshold share one of their first
    n - ceil(t n) + 1, so only these are shuffled, and whole sets are read again for
    the classes that meet.  Any such order is exact; a good one has few meetings.
    """
    grams = _shingles(docs, width)
    heads = _heads(grams, percent).persist(StorageLevel.DISK_ONLY)
    classes = heads.groupBy("same").agg(F.min("doc_id").alias("own"))
    copies = heads.select("doc_id", "n", "same").join(classes, "same").where("doc_id <> own").select("doc_id", "own", "n").persist(StorageLevel.DISK_ONLY)
    ones = heads.select("doc_id", "n", F.posexplode("head").alias("at", "gram")).join(seldom(copies.select("doc_id")), "doc_id", "left_anti")
    groups = ones.repartition("gram").groupBy("gram").agg(F.array_sort(F.collect_list(F.struct("n", "doc_id", "at"))).alias("d")).where("size(d) > 1")
    each = groups.select("d", F.posexplode("d").alias("i", "x")).select("x", F.explode(F.filter(F.slice("d", F.col("i") + 2, F.size("d")), lambda y: 100 * F.col("x.n") >= percent * y["n"])).alias("y"))
    # behind the last shingle that two heads share, at most the rest of the smaller set is shared
    seen = each.groupBy("x.doc_id", "x.n", F.col("y.doc_id").alias("other"), F.col("y.n").alias("m")).agg(F.count("*").alias("c"), F.max("x.at").alias("i"), F.max("y.at").alias("j"))
    most = F.col("c") + F.least(F.col("n") - F.col("i"), F.col("m") - F.col("j")) - 1
    met = seen.where(most * (100 + percent) >= percent * (F.col("n") + F.col("m"))).select(F.least("doc_id", "other").alias("a"), F.greatest("doc_id", "other").alias("b")).persist(StorageLevel.DISK_ONLY)
    sets = lambda side: _shingles(docs.join(seldom(met.select(F.col(side).alias("doc_id")).distinct()), "doc_id", "left_semi"), width)
    other = sets("b").select(F.col("doc_id").alias("b"), F.col("g").alias("y")).join(seldom(met, MEETINGS), "b")
    both = other.join(sets("a").select(F.col("doc_id").alias("a"), F.col("g").alias("x")), "a")
    counted = both.select("a", "b", F.size(F.array_intersect("x", "y")).alias("shared"), (F.size("x") + F.size("y")).alias("total"))
    linked = counted.select("a", "b", F.col("shared").cast("long").alias("shared"), (F.col("total") - F.col("shared")).cast("long").alias("either")).where(f"100 * shared >= {percent} * either")
    # copies take the links of their class, and are linked with each other
    some = copies.select("own", "doc_id", "n").unionByName(copies.select("own", F.col("own").alias("doc_id"), "n").distinct())
    inside = some.alias("p").join(some.alias("q"), "own").where("p.doc_id < q.doc_id").select(F.col("p.doc_id").alias("a"), F.col("q.doc_id").alias("b"), F.col("p.n").cast("long").alias("shared"), F.col("p.n").cast("long").alias("either"))
    member = some.select("own", "doc_id")
    wide = linked.join(member.select(F.col("own").alias("a"), F.col("doc_id").alias("m")), "a", "left").withColumn("m", F.coalesce("m", "a"))
    wide = wide.join(member.select(F.col("own").alias("b"), F.col("doc_id").alias("o")), "b", "left").withColumn("o", F.coalesce("o", "b"))
    return inside.unionByName(wide.select(F.least("m", "o").alias("a"), F.greatest("m", "o").alias("b"), "shared", "either"))


def containment(docs: DataFrame, items: DataFrame, width: int = 8) -> DataFrame:
    """(doc_id, item_id): documents that hold an evaluation text verbatim: shared token windows, then ``contains``."""
    window = lambda df, key: df.select(key, F.explode(F.array_distinct(_runs(F.col("text"), width))).alias("h"))
    some = window(items, "item_id").groupBy("item_id").agg(F.min("h").alias("h"))
    # ids meet first; texts are fetched for the pairs that share a window
    met = window(docs, "doc_id").join(some, "h").select("doc_id", "item_id").distinct()
    both = met.join(items.select("item_id", F.col("text").alias("wanted")), "item_id").join(docs.select("doc_id", "text"), "doc_id")
    return both.where(F.contains(F.col("text"), F.col("wanted"))).select("doc_id", "item_id").distinct()


def _runs(text, width: int):
    def runs(w):
        size = F.greatest(F.least(F.size(w), F.lit(width)), F.lit(1))
        return F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - width + 1, F.lit(1))), lambda i: F.xxhash64(F.array_join(F.slice(w, i, size), " ")))

    return let(token_array(F.coalesce(text, F.lit(""))), runs)
