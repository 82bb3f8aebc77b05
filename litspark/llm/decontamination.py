"""Benchmark decontamination: SimHash of item-sized windows, multi-index Hamming blocks, exact weighted-shingle check.

A document leaks an item if some window of as many words as the item has
(the whole document where it is shorter) has a weighted-shingle similarity of at
least 0.75: the sum of the smaller counts over the sum of the larger counts of
their 5-word shingles.  Words are lower-case runs of letters and digits, so case
and punctuation do not hide a leak; an item of fewer than five words is one
shingle.

1. A similar window shares a shingle with an item of its size.  So in documents
   that hold a shingle of an item, every window of that item's size around such a
   place gets a 64-bit SimHash; a window without any has a similarity of zero.
2. Eight 8-bit blocks of the fingerprint meet those of the items of that size, of
   all of them, that differ by at most two bits in the block, which finds every
   pair within 23 bits (pairs at the similarity bound differ by 11 bits, with a
   standard deviation of 3).  Only these pairs are candidates.
3. Candidates are verified exactly on the full shingles.

All steps are DataFrame expressions; the item side is broadcast only where it is
counted small.

Edge cases: null or empty texts and items have no words and never match; repeated
items or rows each count once (results are distinct); ties go to the first start;
a null doc_id or item_id is carried as null; empty tables give an empty result;
other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from litspark.llm.common import BROADCAST_ROWS, Scratch, small
from litspark.llm.quality_rules import let

WIDTH = 5
SIMILARITY = 75
BLOCKS = 8
BITS = 64 // BLOCKS
BLOCK_RADIUS = 2
RADIUS = (BLOCK_RADIUS + 1) * BLOCKS - 1
#: Rows of the items' shingles or probes that may be broadcast.
BROADCAST_ITEM_ROWS = 500_000
#: Places or windows of documents that may be broadcast with their documents; some tens of bytes each.
BROADCAST_PLACES = 2_000_000
#: The lowest bit of each lane of 16 bits.
LANES = 0x0001000100010001
#: Stands for a null doc_id.
NONE = -(2**63)


def words(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(F.coalesce(text.cast("string"), F.lit(""))), F.lit(r"([\p{L}\p{N}]+)"), F.lit(1))


def grams(tokens: Column, width: int) -> Column:
    """Hashes of all runs of ``width`` words; empty where there are fewer."""

    def runs(h: Column) -> Column:
        first = F.slice(h, F.lit(1), F.greatest(F.size(h) - (width - 1), F.lit(0)))
        return F.transform(first, lambda x, i: F.xxhash64(x, *[F.get(h, i + j) for j in range(1, width)], F.lit(width)))

    return let(F.transform(tokens, lambda w: F.xxhash64(w)), runs)


def simhash(shingles: str) -> str:
    """SQL of the fingerprint of an array<bigint>: bit b is set if most shingles have it.

    One addition counts four bits at once, in lanes of 16 bits, while there are
    fewer than 2^15 shingles; beyond that each bit is counted on its own.
    """
    counts = f"transform(sequence(0, 15), j -> aggregate({shingles}, 0L, (sum, h) -> sum + (shiftrightunsigned(h, j) & {LANES}L)))"
    fast = "aggregate(sequence(0, 63), 0L, (acc, b) -> acc | if(2 * (shiftrightunsigned(c[b & 15], b & 48) & 65535L) > size(%s), shiftleft(1L, b), 0L))" % shingles
    ones = f"size(filter({shingles}, h -> shiftrightunsigned(h, b) & 1L = 1L))"
    slow = f"aggregate(sequence(0, 63), 0L, (acc, b) -> acc | if(2 * {ones} > size({shingles}), shiftleft(1L, b), 0L))"
    return f"if(size({shingles}) < 32768, transform(array({counts}), c -> {fast})[0], {slow})"


def common_weight(a: str, b: str) -> str:
    """SQL of the sum of the smaller counts over the distinct values of two arrays."""
    once = f"size(array_distinct({a})) = size({a})"
    each = f"aggregate(array_distinct({a}), 0, (acc, x) -> acc + least(size(filter({a}, y -> y = x)), size(filter({b}, y -> y = x))))"
    return f"if({once}, size(array_intersect({a}, {b})), {each})"


def _masks() -> list[int]:
    return [m for m in range(1 << BITS) if m.bit_count() <= BLOCK_RADIUS]


def _block(value: Column, k: int) -> Column:
    return F.shiftrightunsigned(value, k * BITS).bitwiseAND(F.lit((1 << BITS) - 1)).cast("int")


def _light(rows: DataFrame) -> DataFrame:
    """``rows`` with a broadcast hint while its rows and their summed ``weight`` are within bounds."""
    held = rows.agg(F.count("*").alias("rows"), F.sum("weight").alias("weight")).first()
    return F.broadcast(rows) if held.rows <= BROADCAST_ROWS and (held.weight or 0) <= BROADCAST_PLACES else rows


def _opened(rows: DataFrame, widths: list[int]) -> DataFrame:
    """One row per span ``s`` of ``rows(text, spans, ...)`` with the shingles of the whole text at the span's width."""
    cut = rows.withColumn("tokens", words(F.col("text")))
    cut = cut.select("doc_id", "pick", "tag", "spans", F.size("tokens").alias("n_tokens"), *[grams(F.col("tokens"), k).alias(f"g{k}") for k in widths])
    one = cut.select("doc_id", "pick", "tag", "n_tokens", F.explode("spans").alias("s"), *[f"g{k}" for k in widths])
    return one.select("doc_id", "pick", "tag", "n_tokens", "s", F.coalesce(*[F.when(F.col("s.width") == k, F.col(f"g{k}")) for k in widths]).alias("grams"))


def leaks(docs: DataFrame, benchmark: DataFrame, percent: int = SIMILARITY) -> DataFrame:
    """(doc_id, tag, item_id, start_word, n_words, similarity) of every leaked pair, at its best window.

    ``docs(doc_id, text)``, ``benchmark(item_id, text)``; tag is the hash of the
    text, so that (doc_id, tag) names the row even where a doc_id repeats.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "leaks")
    said = benchmark.select(F.col("item_id").cast("long").alias("item_id"), words(F.col("text")).alias("w")).where("size(w) > 0").distinct()
    said = said.withColumn("width", F.least(F.size("w"), F.lit(WIDTH)))
    sized = F.coalesce(*[F.when(F.col("width") == k, grams(F.col("w"), k)) for k in range(1, WIDTH + 1)])
    items = scratch.write(said.select("item_id", F.size("w").alias("w"), "width", sized.alias("item_grams")).withColumn("print", F.expr(simhash("item_grams"))))
    widths = sorted(r.width for r in items.select("width").distinct().collect())
    of_sizes = items.select("w", "width", F.explode(F.array_distinct("item_grams")).alias("gram")).distinct()
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("doc_id").cast("long"), F.lit(NONE)).alias("pick"), F.col("text").cast("string").alias("text"))
    source = source.withColumn("tag", F.xxhash64("text"))

    found = None
    for k in widths:
        spots = source.select("pick", "tag", F.posexplode(grams(words(F.col("text")), k)).alias("at", "gram"))
        hit = spots.join(small(of_sizes.where(F.col("width") == k), BROADCAST_ITEM_ROWS), "gram").select("pick", "tag", "w", "width", "at")
        found = hit if found is None else found.unionByName(hit)
    if found is None:
        return spark.createDataFrame([], "doc_id long, tag long, item_id long, start_word int, n_words int, similarity double")
    near = found.groupBy("pick", "tag", "w", "width").agg(F.array_sort(F.collect_set("at")).alias("places"))
    near = scratch.write(near.groupBy("pick", "tag").agg(F.sum(F.size("places")).alias("weight"), F.collect_list(F.struct("w", "width", "places")).alias("spans")))
    kept = scratch.write(source.join(_light(near), ["pick", "tag"]), "kept")

    n = F.col("s.w") - F.col("s.width") + 1
    last = F.greatest(F.col("n_tokens") - F.col("s.w"), F.lit(0))

    def starts(place: Column, i: Column) -> Column:
        """Starts of the windows whose last shared place is this one or a later one, and which no earlier place gave."""
        low = F.greatest(place - n + 1, F.coalesce(F.get(F.col("s.places"), i - 1), F.lit(-1)) + 1)
        high = F.least(place, last)
        return F.when(low <= high, F.sequence(low, high)).otherwise(F.array().cast("array<int>"))

    taken = "slice(grams, start + 1, s.w - s.width + 1)"
    marks = F.expr(f"transform(starts, start -> transform(array({taken}), x -> struct(start as start_word, {simhash('x')} as print))[0])")
    opened = _opened(kept, widths).withColumn("starts", F.flatten(F.transform("s.places", starts)))
    marked = opened.select("pick", "tag", "s.w", F.explode(marks).alias("m")).select("pick", "tag", "w", "m.start_word", "m.print")
    marked = scratch.write(marked, "marked")

    places = lambda value: F.array(*[F.struct(F.lit(k).alias("block"), _block(value, k).alias("bits")) for k in range(BLOCKS)])
    masks = F.array(*[F.lit(m) for m in _masks()])
    probes = items.select("w", F.col("print").alias("item_print"), F.explode(places(F.col("print"))).alias("b")).distinct()
    probes = probes.select("w", "item_print", F.col("b.block").alias("block"), F.explode(masks).alias("mask"), F.col("b.bits").alias("own"))
    probes = probes.select("w", "item_print", "block", F.col("own").bitwiseXOR(F.col("mask")).alias("bits"))
    met = marked.select("pick", "tag", "w", "start_word", "print", F.explode(places(F.col("print"))).alias("b"))
    met = met.select("pick", "tag", "w", "start_word", "print", F.col("b.block").alias("block"), F.col("b.bits").alias("bits"))
    pairs = met.join(small(probes, BROADCAST_ITEM_ROWS), ["w", "block", "bits"]).where(F.bit_count(F.col("print").bitwiseXOR(F.col("item_print"))) <= RADIUS)
    pairs = pairs.groupBy("pick", "tag").agg(F.collect_set(F.struct("w", F.least("w", F.lit(WIDTH)).alias("width"), "start_word", F.col("item_print").alias("print"))).alias("spans"))
    pairs = scratch.write(pairs.withColumn("weight", F.size("spans")), "pairs")

    checked = _opened(kept.drop("spans", "weight").join(_light(pairs), ["pick", "tag"]), widths).withColumn("start", F.col("s.start_word"))
    checked = checked.select("doc_id", "tag", "s.w", "s.print", "s.start_word", F.least("n_tokens", "s.w").alias("n_words"), F.expr(taken).alias("grams"))
    checked = checked.join(small(items.select("item_id", "w", "print", "item_grams")), ["w", "print"])
    checked = checked.withColumn("both", F.expr(common_weight("item_grams", "grams"))).withColumn("either", F.expr("size(item_grams) + size(grams) - both"))
    good = checked.where(f"100 * both >= {percent} * either").withColumn("similarity", F.round(F.col("both") / F.col("either"), 6))
    best = F.min(F.struct((-F.col("similarity")).alias("down"), "start_word", "n_words")).alias("best")
    return good.groupBy("doc_id", "tag", "item_id").agg(best).select("doc_id", "tag", "item_id", "best.start_word", "best.n_words", (-F.col("best.down")).alias("similarity"))


#: DuckDB SQL of the leaks of items of at least five words in ``documents``: every window of every document that shares enough.
ORACLE = r"""
WITH i AS (SELECT item_id, w, list_transform(range(1, len(w) - 3), lambda k: array_to_string(w[k : k + 4], ' ')) AS g FROM (SELECT DISTINCT item_id, regexp_extract_all(lower(coalesce(text, '')), '[\p{L}\p{N}]+') AS w FROM benchmark) WHERE len(w) >= 5),
d AS (SELECT doc_id, len(w) AS n, list_transform(range(1, len(w) - 3), lambda k: array_to_string(w[k : k + 4], ' ')) AS g FROM (SELECT DISTINCT doc_id, regexp_extract_all(lower(coalesce(text, '')), '[\p{L}\p{N}]+') AS w FROM documents) WHERE len(w) >= 5),
met AS (SELECT doc_id, item_id FROM (SELECT doc_id, unnest(g) AS x, generate_subscripts(g, 1) AS place FROM d) JOIN (SELECT DISTINCT item_id, len(g) AS size, unnest(g) AS x FROM i) USING (x) GROUP BY doc_id, item_id, size HAVING 100 * count(DISTINCT place) >= 75 * size),
cut AS (SELECT doc_id, item_id, s::INT AS start_word, least(n, len(w))::INT AS n_words, i.g AS a, d.g[s + 1 : s + len(w) - 4] AS b FROM met JOIN i USING (item_id) JOIN d USING (doc_id), LATERAL (SELECT unnest(range(0, greatest(n - len(w), 0) + 1)) AS s)),
sim AS (SELECT doc_id, item_id, start_word, n_words, len(a) + len(b) AS total, list_sum(list_transform(list_distinct(a), lambda x: least(len(list_filter(a, lambda y: y = x)), len(list_filter(b, lambda y: y = x))))) AS shared FROM cut)
SELECT doc_id, item_id, arg_min(start_word, (-round(shared / (total - shared), 6), start_word)) AS start_word, min(n_words)::INT AS n_words, max(round(shared / (total - shared), 6)) AS similarity
FROM sim WHERE 100 * shared >= 75 * (total - shared) GROUP BY doc_id, item_id
"""
