"""Question-chunk pairs: stand-in questions, corpus composition, and the document-wise held-out split."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from litspark.functions.text import hash_code, token_array

# The opening words of stand-in questions by language.
FRAMES = {"en": "What about", "fr": "Que dire de", "de": "Was ist mit", "es": "Que hay de"}
QUESTION_TOKENS = 8
ACCEPT_TOKENS = 12
HELD_OUT_PERCENT = 5
#: Distinct tokens whose frequencies go to every task; beyond them, those of the ``COMMON`` most frequent.
VOCABULARY, COMMON = 500_000, 20_000


def document_frequency(docs: DataFrame) -> DataFrame:
    """(token, df): in how many documents a token stands."""
    return docs.select(F.explode(F.array_distinct(token_array(F.coalesce("text", F.lit(""))))).alias("token")).groupBy("token").agg(F.count("*").alias("df"))


def synth_questions(chunks: DataFrame, docs: DataFrame, accept: int = ACCEPT_TOKENS, size: int = QUESTION_TOKENS, frequency: DataFrame | None = None) -> DataFrame:
    """(chunk_id, doc_id, question) of the chunks with at least ``accept`` distinct tokens.

    A stand-in for a generated question: the chunk's rarest tokens in reading
    order behind a frame word; rarer means fewer documents, then smaller md5.
    ``frequency`` is the ``document_frequency`` of the documents, if it is held already.
    """
    enough = chunks.select("chunk_id", "doc_id", token_array(F.col("text")).alias("w")).where(F.size(F.array_distinct("w")) >= accept)
    own = frequency is None
    frequency = document_frequency(docs).persist() if own else frequency
    known = frequency.limit(VOCABULARY + 1).count()
    if known <= VOCABULARY:
        # the frequencies go to every task: no token of a chunk is shuffled
        chosen = _rarest_in_place(enough, {r.token: r.df for r in frequency.collect()}, size)  # at most VOCABULARY rows
        if own:
            frequency.unpersist()
    else:
        chosen = _rarest_by_join(enough, frequency, size)
    framed = chosen.join(docs.select("doc_id", "lang"), "doc_id")
    frames = F.create_map(*[F.lit(x) for p in FRAMES.items() for x in p])
    return framed.select("chunk_id", "doc_id", F.concat_ws(" ", F.coalesce(F.try_element_at(frames, F.col("lang")), F.lit("What about")), "reading", F.lit("?")).alias("question"))


def _rarest_by_join(enough: DataFrame, frequency: DataFrame, size: int) -> DataFrame:
    """(chunk_id, doc_id, reading) for any vocabulary.

    Tokens of very many documents are hot keys, so their frequencies, a bounded
    table, are broadcast; the others meet by a shuffle.
    """
    spread = enough.select("chunk_id", "doc_id", F.posexplode(F.array_distinct("w")).alias("at", "token"))
    common = F.broadcast(frequency.orderBy(F.desc("df"), "token").limit(COMMON).withColumnRenamed("df", "often"))
    met = spread.join(common, "token", "left")
    rated = met.where("often is not null").withColumnRenamed("often", "df").unionByName(met.where("often is null").drop("often").join(frequency, "token"))
    best = F.slice(F.array_sort(F.collect_list(F.struct("df", F.md5("token").alias("h"), "at", "token"))), 1, size)
    chosen = rated.groupBy("chunk_id", "doc_id").agg(best.alias("b"))
    reading = F.array_join(F.transform(F.array_sort(F.transform("b", lambda x: F.struct(x["at"].alias("at"), x["token"].alias("token")))), lambda x: x["token"]), " ")
    return chosen.select("chunk_id", "doc_id", reading.alias("reading"))


@lru_cache(maxsize=1 << 16)
def _digest(token: str) -> str:
    return hashlib.md5(token.encode()).hexdigest()


def _rarest_in_place(enough: DataFrame, frequency: dict[str, int], size: int) -> DataFrame:
    """(chunk_id, doc_id, reading) with the frequencies at hand; the same rows as by the join."""
    held = enough.sparkSession.sparkContext.broadcast(frequency)

    def pick(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = held.value
        for batch in rows:
            out = []
            for words in batch.column("w").to_pylist():
                own = [w for w in dict.fromkeys(words) if w in known]
                bound = sorted(known[w] for w in own)[min(size, len(own)) - 1] if own else 0
                rare = sorted((w for w in own if known[w] <= bound), key=lambda w: (known[w], _digest(w)))[:size]
                place = {w: i for i, w in enumerate(own)}
                out.append(" ".join(sorted(rare, key=place.__getitem__)))
            yield pa.RecordBatch.from_arrays([batch.column("chunk_id"), batch.column("doc_id"), pa.array(out, pa.string())], ["chunk_id", "doc_id", "reading"])

    return enough.select("chunk_id", "doc_id", "w").mapInArrow(pick, "chunk_id string, doc_id long, reading string")


def clusters(docs: DataFrame) -> DataFrame:
    """(doc_id, cluster_id): the smallest doc_id with the same text."""
    named = docs.select("doc_id", F.md5("text").alias("digest"))
    return named.join(named.groupBy("digest").agg(F.min("doc_id").alias("cluster_id")), "digest").select("doc_id", "cluster_id")


def in_test(key: Column, percent: int = HELD_OUT_PERCENT) -> Column:
    return hash_code(key.cast("string")) % 100 < percent


def split_by_document(pairs: DataFrame, docs: DataFrame, percent: int = HELD_OUT_PERCENT) -> DataFrame:
    """``pairs(doc_id, ...)`` with split and cluster_id: all pairs of a cluster of equal documents fall on one side."""
    return pairs.join(clusters(docs), "doc_id").withColumn("split", F.when(in_test(F.col("cluster_id"), percent), "test").otherwise("train"))


def split_by_pair(pairs: DataFrame, docs: DataFrame, percent: int = HELD_OUT_PERCENT) -> DataFrame:
    """The leaking alternative: every pair is drawn on its own."""
    return pairs.join(clusters(docs), "doc_id").withColumn("split", F.when(in_test(F.col("chunk_id"), percent), "test").otherwise("train"))


def drawn_pairs(docs: DataFrame, size: int, frequency: DataFrame | None = None) -> DataFrame:
    """(pair_id, chunk_id, question, text): the first ``size`` training pairs in md5 order.

    The same rows as those of all training pairs in this order; they are chosen
    before questions are made, so only theirs are.
    """
    from litspark.operators.chunk import semantic_chunks
    from litspark.operators.index import seldom

    trains = clusters(docs).where(~in_test(F.col("cluster_id"))).select("doc_id")
    made = semantic_chunks(docs.join(seldom(trains), "doc_id", "left_semi")).select("chunk_id", "doc_id", "text", "n_tokens")
    enough = made.where((F.col("n_tokens") >= ACCEPT_TOKENS) & (F.size(F.array_distinct(token_array(F.col("text")))) >= ACCEPT_TOKENS))
    chosen = enough.orderBy(F.md5("chunk_id"), "chunk_id").limit(size).persist(StorageLevel.DISK_ONLY)  # read for the questions and for their texts
    asked = synth_questions(chosen, docs, frequency=frequency)
    return asked.select(F.col("chunk_id").alias("pair_id"), "chunk_id", "question").join(chosen.select("chunk_id", "text"), "chunk_id")


def leakage(split: DataFrame) -> DataFrame:
    """One row: test pairs, and how many of them come from a cluster that also trains."""
    trained = split.where("split = 'train'").select("cluster_id").distinct().withColumn("seen", F.lit(True))
    return split.where("split = 'test'").join(trained, "cluster_id", "left").agg(F.count("*").alias("test_pairs"), F.coalesce(F.sum(F.when(F.col("seen"), 1).otherwise(0)), F.lit(0)).cast("long").alias("leaked_pairs"))


def composition(docs: DataFrame, chunks: DataFrame, questions: DataFrame) -> DataFrame:
    """(source, documents, chunks, questions) per source and in total."""
    per = docs.select("doc_id", "source").join(chunks.groupBy("doc_id").agg(F.count("*").alias("c")), "doc_id", "left").join(questions.groupBy("doc_id").agg(F.count("*").alias("q")), "doc_id", "left")
    summed = per.rollup("source").agg(F.count("*").alias("documents"), F.sum(F.coalesce("c", F.lit(0))).alias("chunks"), F.sum(F.coalesce("q", F.lit(0))).alias("questions"), F.grouping("source").alias("g"))
    return summed.select(F.when(F.col("g") == 1, "Total").otherwise(F.col("source")).alias("source"), "documents", "chunks", "questions")


def subdomain_distribution(docs: DataFrame) -> DataFrame:
    """(source, lang, documents, share of the source)."""
    counted = docs.groupBy("source", "lang").agg(F.count("*").alias("documents"))
    whole = docs.groupBy("source").agg(F.count("*").alias("whole"))
    return counted.join(whole, "source").select("source", "lang", "documents", F.round(F.col("documents") / F.col("whole"), 6).alias("share"))
