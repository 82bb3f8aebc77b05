"""Evaluation sets: graded passages and multiple-choice items, and how they are answered.

Generators are stand-ins for language models: ``small`` counts the distinct
tokens of an option in the context, ``large`` weighs them by rarity.  Without a
context both see only the question, which is the no-retrieval control.
"""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from litspark.functions.text import hash_code, token_array
from litspark.operators.counted import codes, knn_counts
from litspark.operators.index import alike, knn_gemm, seldom
from litspark.operators.pairs import QUESTION_TOKENS, document_frequency

DRAWS = 64
#: Numbers for each distractor that an entity draws first.
FEW = 2
#: The source databases, by return flag.
SOURCES = ("A", "N", "R")
#: Contexts of different questions that may be broadcast.
CONTEXTS = 4096
LEVELS = 10


def _ordered(options: Column, item: Column) -> Column:
    """Options sorted by md5 of (item, option)."""
    return F.transform(F.array_sort(F.transform(options, lambda o: F.struct(F.md5(F.concat_ws("|", item.cast("string"), o)).alias("h"), o.alias("o")))), lambda x: x["o"])


def choices(df: DataFrame) -> DataFrame:
    """``df(item_id, question, truth, wrong)`` to item_id, question, options (joined), answer_idx; only four distinct options pass."""
    whole = df.withColumn("options", _ordered(F.array_distinct(F.concat(F.array("truth"), "wrong")), F.col("item_id"))).where("size(options) = 4")
    return whole.select("item_id", "question", F.array_join("options", " | ").alias("options"), (F.array_position("options", F.col("truth")) - 1).cast("int").alias("answer_idx"))


def merged_edges(lineitem: DataFrame) -> DataFrame:
    """Distinct (entity, interactant) over the three source databases."""
    sources = [lineitem.where(F.col("l_returnflag") == f).select(F.col("l_partkey").alias("entity"), F.col("l_suppkey").alias("interactant")) for f in SOURCES]
    return sources[0].union(sources[1]).union(sources[2]).distinct()


def interaction_qa(lineitem: DataFrame, part: DataFrame, wrong: int = 3, draws: int = DRAWS) -> DataFrame:
    """Which interactant an entity has; distractors are interactants of others that it has not.

    Distractors are the first of ``draws`` numbers hashed from the entity that
    name a foreign interactant, so no entity meets all interactants; an entity
    without enough is dropped.
    """
    edges = merged_edges(lineitem)
    pool = lineitem.where(F.col("l_returnflag").isin(*SOURCES)).select(F.col("l_suppkey").alias("interactant")).distinct().persist(StorageLevel.DISK_ONLY)
    indexed = seldom(pool.withColumn("at", F.row_number().over(Window.orderBy("interactant")) - 1))  # interactants only
    size = pool.agg(F.count("*").alias("pool"))
    entities = edges.groupBy("entity").agg(F.count("*").alias("known"), F.min_by("interactant", F.struct(F.md5(F.concat_ws("-", "entity", "interactant")).alias("h"), "interactant")).alias("truth")).persist(StorageLevel.DISK_ONLY)

    def first(some: DataFrame, draws: int) -> DataFrame:
        """(entity, wrong) of the entities that have enough among the first ``draws`` numbers."""
        drawn = some.select("entity", F.posexplode(F.sequence(F.lit(1), F.lit(draws))).alias("n", "d")).crossJoin(F.broadcast(size))
        drawn = drawn.select("entity", "n", (hash_code(F.concat_ws("-", "entity", "d")) % F.col("pool")).alias("at")).groupBy("entity", "at").agg(F.min("n").alias("n"))
        foreign = drawn.join(indexed, "at").join(edges, ["entity", "interactant"], "left_anti")
        ranked = foreign.withColumn("r", F.row_number().over(Window.partitionBy("entity").orderBy("n"))).where(F.col("r") <= wrong)
        return ranked.groupBy("entity").agg(F.collect_list(F.concat(F.lit("supplier "), "interactant")).alias("wrong")).where(F.size("wrong") == wrong)

    # what the first few numbers give, more numbers don't change: only entities without enough draw them all
    soon = min(draws, FEW * wrong)
    three = first(entities, soon).persist(StorageLevel.DISK_ONLY)
    rest = entities.join(three, "entity", "left_anti")
    if soon < draws and not rest.isEmpty():
        three = three.unionByName(first(rest, draws))
    named = entities.join(three, "entity").join(part.select(F.col("p_partkey").alias("entity"), "p_name"), "entity")
    asked = F.concat(F.lit("Which supplier provides part "), "entity", F.lit(" "), "p_name", F.lit("?"))
    return choices(named.select(F.col("entity").alias("item_id"), asked.alias("question"), F.concat(F.lit("supplier "), "truth").alias("truth"), "wrong"))


def function_qa(part: DataFrame) -> DataFrame:
    """What an entity is for; distractors are three other functions."""
    kinds = part.select("p_type").where("p_type is not null").distinct()
    every = kinds.agg(F.array_sort(F.collect_set("p_type")).alias("kinds"))  # the functions, a handful
    named = part.select("p_partkey", "p_name", "p_type").crossJoin(F.broadcast(every))
    others = F.slice(_ordered(F.array_remove("kinds", F.col("p_type")), F.concat(F.lit("w"), F.col("p_partkey"))), 1, 3)
    asked = F.concat(F.lit("What is the type of part "), "p_partkey", F.lit(" "), "p_name", F.lit("?"))
    return choices(named.select(F.col("p_partkey").alias("item_id"), asked.alias("question"), F.col("p_type").alias("truth"), others.alias("wrong")))


def fact_passages(part: DataFrame, lineitem: DataFrame) -> DataFrame:
    """(passage_id, text): what is known of each entity."""
    known = merged_edges(lineitem).groupBy("entity").agg(F.array_join(F.transform(F.array_sort(F.collect_list("interactant")), lambda s: F.concat(F.lit("supplier "), s)), ", ").alias("known"))
    text = F.concat(F.lit("Part "), "p_partkey", F.lit(" "), "p_name", F.lit(" is of type "), "p_type", F.lit(" and comes from "), "known", F.lit("."))
    return part.join(known, F.col("p_partkey") == F.col("entity")).select(F.col("p_partkey").alias("passage_id"), text.alias("text"))


def rarest(items: DataFrame, docs: DataFrame, key: str, size: int, frequency: DataFrame | None = None) -> DataFrame:
    """(key, words): the ``size`` rarest distinct tokens of each text, in reading order."""
    spread = items.select(key, F.posexplode(F.array_distinct(token_array(F.col("text")))).alias("at", "token"))
    rated = spread.join(document_frequency(docs) if frequency is None else frequency, "token", "left").withColumn("df", F.coalesce("df", F.lit(0)))
    best = F.slice(F.array_sort(F.collect_list(F.struct("df", F.md5("token").alias("h"), "at", "token"))), 1, size)
    chosen = rated.groupBy(key).agg(best.alias("b"))
    return chosen.select(key, F.transform(F.array_sort(F.transform("b", lambda x: F.struct(x["at"].alias("at"), x["token"].alias("token")))), lambda x: x["token"]).alias("words"))


def graded_set(benchmark: DataFrame, levels: int = LEVELS) -> DataFrame:
    """(question_id, subdomain, passage_id, grade, text): ten passages per item of falling relevance.

    Grade g swaps g tenths of the tokens, at positions in md5 order, for those
    at the same positions of item (id + 1 + g) modulo the number of items.
    """
    n = benchmark.agg(F.count("*").alias("items"))
    toks = benchmark.select("item_id", token_array(F.col("text")).alias("w")).where("size(w) > 0")
    graded = toks.crossJoin(F.broadcast(n)).select("item_id", "w", F.explode(F.sequence(F.lit(0), F.lit(levels - 1))).alias("grade"), "items")
    other = toks.select(F.col("item_id").alias("other_id"), F.col("w").alias("v"))
    pairs = graded.withColumn("other_id", (F.col("item_id") + 1 + F.col("grade")) % F.col("items")).join(other, "other_id")
    places = F.transform(F.array_sort(F.transform(F.sequence(F.lit(0), F.size("w") - 1), lambda p: F.struct(F.md5(F.concat_ws("|", "item_id", "grade", p)).alias("h"), p.alias("p")))), lambda x: x["p"])
    swapped = F.slice(places, F.lit(1), F.floor(F.col("grade") * F.size("w") / levels).cast("int"))
    marked = pairs.withColumn("swapped", swapped)
    text = F.array_join(F.transform("w", lambda x, i: F.when(F.array_contains("swapped", i), F.get(F.col("v"), i % F.size("v"))).otherwise(x)), " ")
    return marked.select(
        F.col("item_id").alias("question_id"), F.concat(F.lit("s"), F.pmod("item_id", F.lit(20))).alias("subdomain"), (F.col("item_id") * levels + F.col("grade")).alias("passage_id"), "grade", text.alias("text")
    )


def graded_questions(benchmark: DataFrame, docs: DataFrame, frequency: DataFrame | None = None) -> DataFrame:
    """(query_id, question) for the graded set."""
    return rarest(benchmark, docs, "item_id", QUESTION_TOKENS, frequency).select(F.col("item_id").alias("query_id"), F.array_join("words", " ").alias("question"))


def validate_graded(graded: DataFrame, questions: DataFrame) -> DataFrame:
    """(question_id, ordered): whether overlap with the question never rises from grade 0 to the last, beyond one token."""
    q = questions.select(F.col("query_id").alias("question_id"), F.split("question", " ").alias("q"))
    overlap = graded.join(q, "question_id").select("question_id", "grade", F.size(F.array_intersect("q", token_array(F.col("text")))).alias("o"))
    order = Window.partitionBy("question_id").orderBy("grade")
    return overlap.withColumn("before", F.lag("o").over(order)).groupBy("question_id").agg(F.bool_and(F.coalesce(F.col("o") <= F.col("before") + 1, F.lit(True))).alias("ordered"))


def cloze_qa(benchmark: DataFrame, docs: DataFrame, frequency: DataFrame | None = None) -> DataFrame:
    """The rarest token of an item is left out; the options are the rarest tokens of three other items."""
    key = rarest(benchmark, docs, "item_id", 1, frequency).select("item_id", F.get("words", F.lit(0)).alias("word"))
    n = benchmark.agg(F.count("*").alias("items"))
    wanted = key.crossJoin(F.broadcast(n)).select("item_id", F.explode(F.sequence(F.lit(1), F.lit(3))).alias("d"), "items").withColumn("other_id", (F.col("item_id") + F.col("d")) % F.col("items"))
    wrong = wanted.join(key.select(F.col("item_id").alias("other_id"), F.col("word").alias("other")), "other_id").groupBy("item_id").agg(F.collect_list("other").alias("wrong"))
    gap = F.array_join(F.transform(token_array(F.col("text")), lambda w: F.when(w == F.col("word"), "_").otherwise(w)), " ")
    return choices(benchmark.join(key, "item_id").join(wrong, "item_id").select("item_id", gap.alias("question"), F.col("word").alias("truth"), "wrong"))


def yesno_qa(labels: DataFrame, docs: DataFrame) -> DataFrame:
    """Whether a labelled document is sound; the context is needed. Options are always no, yes."""
    return labels.where("quality is not null").join(docs.select("doc_id"), "doc_id").select(F.col("doc_id").alias("item_id"), F.concat(F.lit("Is document "), "doc_id", F.lit(" sound?")).alias("question"), F.lit("no | yes").alias("options"), F.col("quality").alias("answer_idx"))


def fulltext_qa(docs: DataFrame, beyond: int = 1000) -> DataFrame:
    """Which sentence stands in a document beyond its first ``beyond`` characters; distractors come from the next three such documents."""
    from litspark.functions.text import SENTENCE_END

    tail = F.filter(F.split(F.substring("text", beyond + 1, 2**31 - 1), SENTENCE_END), lambda s: s.rlike(r"\S"))
    long = docs.where(F.length("text") > beyond).select("doc_id", "lang", F.get(tail, F.lit(1)).alias("s")).where("s is not null")
    order = Window.partitionBy("lang").orderBy("doc_id")
    near = long.select("doc_id", "s", F.array(*[F.lead("s", k).over(order) for k in (1, 2, 3)]).alias("wrong")).where(~F.exists("wrong", lambda x: x.isNull()))
    return choices(near.select(F.col("doc_id").alias("item_id"), F.concat(F.lit("What does document "), "doc_id", F.lit(" say?")).alias("question"), F.col("s").alias("truth"), "wrong"))


def answers(items: DataFrame, contexts: DataFrame | None, frequency: DataFrame | None = None) -> DataFrame:
    """(item_id, chosen, answer_idx, correct) of ``items`` given ``contexts(item_id, context)``; ``frequency(token, df)`` weighs tokens by rarity.

    An option's score is the (weighted) number of its distinct tokens in the
    context, or in the question where there is none; ties go to the first option.
    Where ``contexts`` has their ``words`` too, these are taken.
    """
    seen = items.withColumn("context", F.col("question")) if contexts is None else items.join(contexts, "item_id", "left").withColumn("context", F.coalesce("context", "question"))
    words = token_array(F.col("context"))
    words = F.coalesce("words", words) if "words" in seen.columns else words
    options = seen.select("item_id", "answer_idx", words.alias("c"), F.posexplode(F.split("options", r" \| ")).alias("i", "option"))
    if frequency is None:
        scored = options.select("item_id", "answer_idx", "i", F.size(F.array_intersect(F.array_distinct(token_array(F.col("option"))), "c")).cast("double").alias("score"))
    else:
        hit = options.select("item_id", "answer_idx", "i", F.explode_outer(F.array_intersect(F.array_distinct(token_array(F.col("option"))), "c")).alias("token"))
        weight = F.when(F.col("token").isNull(), 0.0).otherwise(1 / (1 + F.coalesce("df", F.lit(0))))
        said = items.select(F.explode(F.array_distinct(token_array(F.col("options")))).alias("token")).distinct()
        scored = hit.join(seldom(frequency.join(said, "token", "left_semi")), "token", "left").groupBy("item_id", "answer_idx", "i").agg(F.sum(weight).alias("score"))
    best = scored.groupBy("item_id", "answer_idx").agg(F.max_by("i", F.struct("score", (-F.col("i")).alias("first"))).alias("chosen"))
    return best.select("item_id", F.col("chosen").cast("int").alias("chosen"), "answer_idx", (F.col("chosen") == F.col("answer_idx")).alias("correct"))


def augment(questions: DataFrame, hits: DataFrame, passages: DataFrame, budget: int = 4000) -> DataFrame:
    """(item_id, context): passages of ``hits(query_id, rank, id)`` in rank order, cut at ``budget`` characters."""
    told = hits.join(passages.select(F.col("passage_id").alias("id"), "text"), "id")
    listed = told.groupBy(F.col("query_id").alias("item_id")).agg(F.array_sort(F.collect_list(F.struct("rank", "text"))).alias("p"))
    joined = listed.select("item_id", F.substring(F.array_join(F.transform("p", lambda x: x["text"]), " "), 1, budget).alias("context"))
    return questions.select("item_id").join(joined, "item_id", "left")


def found_contexts(questions: DataFrame, queries: DataFrame, vectors: DataFrame, passages: DataFrame, k: int) -> DataFrame:
    """(item_id, context) of ``questions`` from the k nearest passages of their vectors; equal vectors are asked, and their passages joined, once."""
    stand, members = alike(queries)
    asked = stand.select(F.col("query_id").alias("item_id"))
    told = augment(asked, knn_gemm(stand, vectors, k), passages).withColumnRenamed("item_id", "own").persist(StorageLevel.DISK_ONLY)
    return questions.select("item_id").join(members.withColumnRenamed("query_id", "item_id"), "item_id", "left").join(seldom(told, CONTEXTS), "own", "left").select("item_id", "context")


def hashed_contexts(questions: DataFrame, passages: DataFrame, dims: int, k: int) -> DataFrame:
    """``found_contexts`` by hashed counts, and the distinct ``words`` of each context: (item_id, context, words).

    Equal vectors are grouped by their codes, and neither vectors nor the tokens of a
    context are made for each of their questions.
    """
    named = codes(questions, "question", "item_id", dims).persist(StorageLevel.DISK_ONLY)
    stand = named.groupBy("code").agg(F.min("id").alias("own")).persist(StorageLevel.DISK_ONLY)
    hits = knn_counts(stand.select(F.col("own").alias("query_id"), "code"), passages, "text", "passage_id", k, dims).persist(StorageLevel.DISK_ONLY)
    told = augment(stand.select(F.col("own").alias("item_id")), seldom(hits), passages).withColumnRenamed("item_id", "own")
    told = told.withColumn("words", F.array_distinct(token_array(F.col("context")))).persist(StorageLevel.DISK_ONLY)
    members = named.join(seldom(stand), "code").select(F.col("id").alias("item_id"), "own")
    return questions.select("item_id").join(members, "item_id", "left").join(seldom(told, CONTEXTS), "own", "left").select("item_id", "context", "words")


def accuracy(graded: DataFrame) -> DataFrame:
    return graded.agg(F.count("*").alias("items"), F.sum(F.col("correct").cast("long")).alias("correct"), F.round(F.avg(F.col("correct").cast("double")), 6).alias("accuracy"))
