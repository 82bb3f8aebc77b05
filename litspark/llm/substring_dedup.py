"""Passages that an earlier document already holds: relative Lempel-Ziv factors over an index of all documents.

A document is factored against the documents with a smaller doc_id: a factor is
a maximal run of words that continues one reference (document, word position).
The reference of a place is looked up in an index of all windows of ``width``
words, so a factor is at least that long; where a factor ends, the windows that
straddle its end have been looked up on their own, so a span that goes on in
another reference is not missed.  What is removed is the union of the factors.

1. One pass names each word sequence (128 bits) and takes its *anchors*: of the
   nine 5-word hashes inside a 13-word window the smallest one.  Equal windows
   have equal anchors, and about a fifth of the positions are anchors, so the
   index is first decided on a fifth of the data.  Equal sequences collapse to
   the smallest doc_id; the others are duplicate as a whole.
2. Anchors seen under two doc_ids at least are the *shared* ones.  Only documents
   that hold some are read again, and only windows on shared anchors are indexed.
3. The index keeps for each window its first document and position (a document
   sends a repeated window once, with all its places); each document
   gets the references of its windows back and is parsed into factors.
4. A last pass cuts the spans out of the texts.

Windows are named by 96 bits from two hashes of their words: among 10^13 of them
one pair of different ones shares a name with a probability below 10^-3.
Every window is judged on the input.  No block is skipped and no list is capped.

Edge cases: null and empty texts have no words and lose none; texts shorter than
a window lose none; a null doc_id counts as larger than any other and equal to
another null; rows that repeat a doc_id are judged alike and never against each
other; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from litspark.llm.common import Scratch, join_split, small, text_batches
from litspark.llm.words import hash_words, mix, set_digest, split_words, window_hashes

WIDTH = 13
GRAM = 5
BATCH = 256
#: Anchors of the documents to be read again that may be broadcast with their documents.
BROADCAST_ANCHORS = 4_000_000
#: Factors whose places may be broadcast to the texts that they are cut from; about eight bytes each.
BROADCAST_FACTORS = 4_000_000
#: Rows of a few longs each that may be broadcast: at most about 80 MB.
KEY_ROWS = 1_000_000
#: Makes the second hash of a word.
SECOND = np.uint64(0xA0761D6478BD642F)
LAST = 2**63 - 1


def anchors(hashes: np.ndarray, width: int, gram: int) -> np.ndarray:
    """For every window of ``width`` words its anchor: the smallest of its ``gram``-word hashes."""
    grams = window_hashes(hashes, gram)
    count = len(hashes) - width + 1
    if count <= 0:
        return np.empty(0, np.uint64)
    low = grams[:count].copy()
    for j in range(1, width - gram + 1):
        np.minimum(low, grams[j : j + count], out=low)
    return low


def _sliced(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in rows:
        for at in range(0, batch.num_rows, BATCH):
            yield batch.slice(at, BATCH)


def _lists(parts: list[np.ndarray], kind: pa.DataType) -> pa.ListArray:
    ends = np.cumsum([0, *map(len, parts)]).astype(np.int32)
    flat = np.concatenate(parts) if parts else np.empty(0, np.int64)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat, kind))


def _profiles(rows: Iterator[pa.RecordBatch], width: int, gram: int) -> Iterator[pa.RecordBatch]:
    for batch in _sliced(rows):
        hashes = [hash_words(split_words(t)) for t in batch.column("text").to_pylist()]
        own = [np.unique(anchors(h, width, gram)).view(np.int64) for h in hashes]
        yield pa.RecordBatch.from_arrays(
            [
                batch.column("doc"),
                batch.column("tag"),
                pa.array([set_digest(h) for h in hashes], pa.binary()),
                pa.array([len(h) for h in hashes], pa.int64()),
                _lists(own, pa.int64()),
            ],
            ["doc", "tag", "digest", "n", "anchors"],
        )


def _windows(rows: Iterator[pa.RecordBatch], width: int, gram: int) -> Iterator[pa.RecordBatch]:
    for batch in _sliced(rows):
        found, checks, places, more = [], [], [], []
        for text, shared in zip(batch.column("text").to_pylist(), batch.column("shared")):
            hashes = hash_words(split_words(text))
            at = np.flatnonzero(np.isin(anchors(hashes, width, gram), shared.values.to_numpy().view(np.uint64)))
            own = window_hashes(hashes, width)[at]
            again = window_hashes(mix(hashes ^ SECOND), width)[at].astype(np.uint32).view(np.int32)
            order = np.lexsort((again, own))
            own, again, at = own[order], again[order], at[order]
            fresh = np.flatnonzero(np.append(True, (own[1:] != own[:-1]) | (again[1:] != again[:-1]))) if len(own) else np.empty(0, np.int64)
            found.append(own[fresh].view(np.int64))
            checks.append(again[fresh])
            places.append(at[fresh].astype(np.int32))
            runs = np.split(at.astype(np.int32), fresh[1:]) if len(own) else []
            more.append([r[1:].tolist() if len(r) > 1 else None for r in runs])
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc"), batch.column("name"), _lists(found, pa.int64()), _lists(checks, pa.int32()), _lists(places, pa.int32()), pa.array(more, pa.list_(pa.list_(pa.int32())))],
            ["doc", "name", "hashes", "checks", "places", "more"],
        )


def factor(places: np.ndarray, docs: np.ndarray, starts: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Maximal runs of referenced windows: (start, words, reference document, reference position)."""
    order = np.lexsort((docs, places))
    places, docs, starts = places[order], docs[order], starts[order]
    fresh = np.ones(len(places), bool)
    fresh[1:] = (places[1:] != places[:-1] + 1) | (docs[1:] != docs[:-1]) | (starts[1:] != starts[:-1] + 1)
    at = np.flatnonzero(fresh)
    long = np.diff(np.append(at, len(places))) + width - 1
    return places[at], long, docs[at], starts[at]


def _factors(rows: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    for batch in _sliced(rows):
        parsed = []
        for refs in batch.column("refs"):
            held = refs.values
            place, doc, start, more = (held.field(c) for c in ("place", "ref_doc", "ref_place", "more"))
            place, doc, start = place.to_numpy(), doc.to_numpy(), start.to_numpy()
            if more.null_count < len(more):  # windows that the document repeats
                times = more.value_lengths().fill_null(0).to_numpy()
                place, doc, start = np.append(place, more.flatten().to_numpy()), np.append(doc, np.repeat(doc, times)), np.append(start, np.repeat(start, times))
            parsed.append(factor(place, doc, start, width))
        yield pa.RecordBatch.from_arrays(
            [batch.column("digest"), *(_lists([p[i] for p in parsed], k) for i, k in enumerate((pa.int32(), pa.int32(), pa.int64(), pa.int32())))],
            ["digest", "starts", "lengths", "ref_docs", "ref_starts"],
        )


def _cut(rows: Iterator[pa.RecordBatch], with_text: bool) -> Iterator[pa.RecordBatch]:
    for batch in _sliced(rows):
        counts, removed, digests, kept = [], [], [], []
        for text, whole, starts, lengths in zip(*(batch.column(c).to_pylist() for c in ("text", "whole", "starts", "lengths"))):
            words = split_words(text)
            counts.append(len(words))
            if whole:
                words = []
            elif starts:
                gone = np.zeros(len(words) + 1, np.int64)
                np.add.at(gone, starts, 1)
                np.add.at(gone, np.add(starts, lengths), -1)
                gone = np.cumsum(gone)
                words = [w for w, g in zip(words, gone.tolist()) if not g]
            removed.append(counts[-1] - len(words))
            joined = b" ".join(words)
            digests.append(hashlib.sha256(joined).hexdigest())
            if with_text:
                kept.append(joined.decode("utf-8", "surrogatepass") if removed[-1] else text)
        columns = [batch.column("doc_id"), pa.array(counts, pa.int64()), pa.array(removed, pa.int64()), pa.array(digests)]
        names = ["doc_id", "n_words", "n_removed", "kept_sha256"]
        yield pa.RecordBatch.from_arrays([*columns, pa.array(kept, pa.string())] if with_text else columns, [*names, "kept_text"] if with_text else names)


def duplicate_factors(docs: DataFrame, width: int = WIDTH, gram: int = GRAM, scratch: Scratch | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(rows, classes, factors) of ``docs(doc, tag, text)``.

    rows: doc, tag, digest, n of every row; classes: digest, first (smallest doc
    of that word sequence), tag (of one of its rows), rows; factors: digest,
    starts, lengths, ref_docs, ref_starts, for the first document of each sequence.
    """
    text_batches(docs.sparkSession)
    scratch = scratch or Scratch(docs.sparkSession, "substring")
    profiles = scratch.write(docs.mapInArrow(lambda rows: _profiles(rows, width, gram), "doc long, tag long, digest binary, n long, anchors array<long>"), "profiles")
    classes = profiles.groupBy("digest").agg(F.min(F.struct("doc", "tag")).alias("who"), F.count("*").alias("rows"))
    classes = scratch.write(classes.select("digest", F.col("who.doc").alias("first"), F.col("who.tag").alias("tag"), "rows"), "classes")
    rows = profiles.select("doc", "tag", "digest", "n")
    # (first, name) tells classes apart; name is 0 but where two sequences share a doc_id
    twice = scratch.write(classes.groupBy("first").agg(F.count("*").alias("count")).where("count > 1").select("first"))
    named = classes.join(small(twice.withColumn("again", F.lit(True))), "first", "left").withColumn("name", F.when(F.col("again"), F.xxhash64("digest")).otherwise(F.lit(0).cast("long"))).drop("again")
    # anchors stay in the profiles: the first row of each class is picked there
    picked = profiles.select("doc", "tag", "anchors").join(small(named.select(F.col("first").alias("doc"), "tag", "name"), KEY_ROWS), ["doc", "tag"])
    spread = picked.select("name", F.col("doc").alias("first"), "tag", F.explode("anchors").alias("anchor"))
    shared = scratch.write(spread.groupBy("anchor").agg(F.min("first").alias("low"), F.max("first").alias("high")).where("low <> high").select("anchor"))
    holders = scratch.write(
        spread.join(small(shared, BROADCAST_ANCHORS), "anchor", "left_semi").groupBy("name", "first", "tag").agg(F.collect_set("anchor").alias("shared"))
    )
    many = holders.agg(F.sum(F.size("shared"))).first()[0] or 0
    side = holders.select(F.col("first").alias("doc"), "tag", "name", "shared")
    again = docs.join(F.broadcast(side) if many <= BROADCAST_ANCHORS else side, ["doc", "tag"]).select("doc", "name", "text", "shared")
    kept = "doc long, name long, hashes array<long>, checks array<int>, places array<int>, more array<array<int>>"
    windows = scratch.write(again.mapInArrow(lambda rows: _windows(rows, width, gram), kept), "windows")
    spots = windows.select("doc", "name", F.explode(F.arrays_zip("hashes", "checks", "places", "more")).alias("w"))
    spots = spots.select("doc", "name", F.col("w.hashes").alias("hash"), F.col("w.checks").alias("check"), F.col("w.places").alias("place"), F.col("w.more").alias("more"))
    index = spots.groupBy("hash", "check").agg(F.min(F.struct("doc", "place")).alias("ref"), F.max("doc").alias("high")).where("ref.doc <> high")
    refs = spots.join(index.select("hash", "check", F.col("ref.doc").alias("ref_doc"), F.col("ref.place").alias("ref_place")), ["hash", "check"]).where("ref_doc < doc")
    refs = refs.groupBy("doc", "name").agg(F.collect_set(F.struct("place", "ref_doc", "ref_place", "more")).alias("refs"))
    factors = refs.join(named.select(F.col("first").alias("doc"), "name", "digest"), ["doc", "name"]).select("digest", "refs")
    factors = scratch.write(factors.mapInArrow(lambda rows: _factors(rows, width), "digest binary, starts array<int>, lengths array<int>, ref_docs array<long>, ref_starts array<int>"), "factors")
    return rows, classes, factors


def substring_dedup(docs: DataFrame, width: int = WIDTH, gram: int = GRAM, with_text: bool = True) -> DataFrame:
    """One row per row of ``docs(doc_id, text)``: doc_id, n_words, n_removed, kept_sha256 and kept_text.

    kept_text is the text itself where nothing is removed, else the kept words
    joined by one space.
    """
    scratch = Scratch(docs.sparkSession, "substring")
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    source = source.withColumns({"doc": F.coalesce("doc_id", F.lit(LAST)), "tag": F.xxhash64("text")})
    rows, classes, factors = duplicate_factors(source.select("doc", "tag", "text"), width, gram, scratch)
    # rows that share a word sequence: copies go as a whole, and what is cut from the first row is cut from its twins under the same doc_id
    many = classes.where("rows > 1").select("digest", "first", F.col("tag").alias("own"), "rows")
    shared = join_split(rows, many, "digest", "rows")
    whole = shared.where((F.col("doc") > F.col("first")) & (F.col("n") >= width)).select("doc", "tag", F.lit(True).alias("whole"), F.lit(None).cast("array<int>").alias("starts"), F.lit(None).cast("array<int>").alias("lengths")).distinct()
    twins = shared.where((F.col("doc") == F.col("first")) & (F.col("tag") != F.col("own"))).select("digest", "doc", "tag").distinct()
    heads = classes.select("digest", F.col("first").alias("doc"), "tag").unionByName(twins)
    part = heads.join(factors.select("digest", "starts", "lengths"), "digest").select("doc", "tag", F.lit(False).alias("whole"), "starts", "lengths")
    acted = scratch.write(whole.unionByName(part), "acted")
    found = acted.agg(F.count("*").alias("rows"), F.sum(F.size(F.coalesce("starts", F.array().cast("array<int>")))).alias("factors")).first()
    side = F.broadcast(acted) if found.rows <= KEY_ROWS and (found.factors or 0) <= BROADCAST_FACTORS else acted
    joined = source.join(side, ["doc", "tag"], "left").select("doc_id", "text", F.coalesce("whole", F.lit(False)).alias("whole"), "starts", "lengths")
    schema = "doc_id long, n_words long, n_removed long, kept_sha256 string" + ", kept_text string" * with_text
    return joined.mapInArrow(lambda rows: _cut(rows, with_text), schema)


#: DuckDB SQL of the query's result on ``documents``: the smallest document of every window, and the words that windows cover.
ORACLE = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
p AS (SELECT doc_id, i, array_to_string(w[i : i + 12], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 11)) AS i FROM w WHERE len(w) >= 13)),
f AS (SELECT g, min(doc_id) AS low FROM p GROUP BY g),
d AS (SELECT p.doc_id, list(DISTINCT p.i) AS starts FROM p JOIN f ON p.g = f.g AND f.low < p.doc_id GROUP BY p.doc_id),
c AS (SELECT doc_id, list_distinct(flatten(list_transform(starts, lambda s: range(s, s + 13)))) AS gone FROM d),
k AS (SELECT w.doc_id, w, CASE WHEN gone IS NULL THEN w ELSE list_transform(list_filter(range(1, len(w) + 1), lambda i: NOT list_contains(gone, i)), lambda i: w[i]) END AS kept FROM w LEFT JOIN c USING (doc_id))
SELECT doc_id, len(w)::BIGINT AS n_words, (len(w) - len(kept))::BIGINT AS n_removed, sha256(array_to_string(kept, ' ')) AS kept_sha256 FROM k
"""
