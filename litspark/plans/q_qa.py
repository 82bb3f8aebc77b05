"""Queries on evaluation sets, retrieval measures, answering and training, with their SQL."""

from __future__ import annotations

from functools import reduce

from pyspark import StorageLevel
from pyspark.sql import functions as F

from litspark.catalog import load
from litspark.functions.measures import ranking_measures
from litspark.functions.text import sql_code, sql_tokens
from litspark.operators import chunk, encode, index, pairs, qa, train
from litspark.plans.q_chunks import QUESTIONS, _clusters, _test

DIMS = 64
FACT_DIMS = 512
TOP = 5


def _t(spark, sf_dir, name, *columns):
    return load(spark, sf_dir, name, *columns)


def _docs(spark, sf_dir):
    return _t(spark, sf_dir, "documents", "doc_id", "text", "lang")


def _interaction(spark, sf_dir):
    return qa.interaction_qa(_t(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey", "l_returnflag"), _t(spark, sf_dir, "part", "p_partkey", "p_name"))


def _function(spark, sf_dir):
    return qa.function_qa(_t(spark, sf_dir, "part", "p_partkey", "p_name", "p_type"))


def _facts(spark, sf_dir):
    return qa.fact_passages(_t(spark, sf_dir, "part", "p_partkey", "p_name", "p_type"), _t(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey", "l_returnflag"))


def _cloze(spark, sf_dir, frequency=None):
    return qa.cloze_qa(_t(spark, sf_dir, "benchmark"), _docs(spark, sf_dir), frequency)


def _yesno(spark, sf_dir):
    return qa.yesno_qa(_t(spark, sf_dir, "labels", "doc_id", "quality"), _docs(spark, sf_dir))


def _fulltext(spark, sf_dir):
    return qa.fulltext_qa(_docs(spark, sf_dir))


def _graded(spark, sf_dir):
    return qa.graded_set(_t(spark, sf_dir, "benchmark"))


def _graded_questions(spark, sf_dir, frequency=None):
    return qa.graded_questions(_t(spark, sf_dir, "benchmark"), _docs(spark, sf_dir), frequency)


def q_validate(spark, sf_dir):
    return qa.validate_graded(_graded(spark, sf_dir), _graded_questions(spark, sf_dir)).groupBy("ordered").agg(F.count("*").alias("questions"))


def _measure_graded(k, encoder=None):
    """P@k counts any passage of the question; MRR@k the grade-0 one."""

    def query(spark, sf_dir, encoder=encoder):
        graded, asked = _graded(spark, sf_dir), _graded_questions(spark, sf_dir)
        embed = encoder or (lambda df, text, key: encode.hashed_vectors(df, text, key, DIMS))
        vectors = embed(graded, "text", "passage_id")
        queries = embed(asked, "question", "query_id").select(F.col("id").alias("query_id"), "vector")
        ranked = index.knn_gemm(queries, vectors, k)
        every = graded.select(F.col("question_id").alias("query_id"), F.col("passage_id").alias("id"))
        any_grade = ranking_measures(asked, ranked, every, k).select("queries", "precision")
        best = ranking_measures(asked, ranked, graded.where("grade = 0").select(F.col("question_id").alias("query_id"), F.col("passage_id").alias("id")), k)
        return any_grade.crossJoin(best.select("mrr", "hit_rate"))  # one row beside one row

    return query


def chunk_number():
    return F.element_at(F.split("chunk_id", "-"), 1).cast("long") * 100_000 + F.element_at(F.split("chunk_id", "-"), 2).cast("long")


def held_out(docs, frequency=None):
    """(chunks, questions) of the held-out documents alone: chunks(id, text, ...) and questions(query_id, question, ...)."""
    test = pairs.clusters(docs).where(pairs.in_test(F.col("cluster_id"))).select("doc_id").persist(StorageLevel.DISK_ONLY)
    made = chunk.semantic_chunks(docs.join(index.seldom(test), "doc_id", "left_semi")).withColumn("id", chunk_number()).persist(StorageLevel.DISK_ONLY)  # read for the questions and for their own vectors
    asked = pairs.synth_questions(made, docs, frequency=frequency).withColumn("query_id", chunk_number()).persist(StorageLevel.DISK_ONLY)
    return made, asked


def with_own(asked, made, embed):
    """(query_id, vector, own): each question's vector and that of its own chunk."""
    queries = embed(asked, "question", "query_id").select(F.col("id").alias("query_id"), "vector")
    return queries.join(embed(made, "text", "id").select(F.col("id").alias("query_id"), F.col("vector").alias("own")), "query_id")


def hashed_parts(docs):
    """Vectors of all chunks by hashed counts, in the parts of the search's rounds; made when they are met and kept nowhere."""
    return [chunk.chunk_vectors(part, dims=DIMS).select((F.col("doc_id") * 100_000 + F.col("chunk_no")).alias("id"), "vector") for part in index.rounds(docs, "doc_id")]


def _heldout(spark, sf_dir, k=20):
    docs = _docs(spark, sf_dir)
    made, asked = held_out(docs)
    ranked = index.own_ranks(with_own(asked, made, lambda df, text, key: encode.hashed_vectors(df, text, key, DIMS)), hashed_parts(docs), k)
    return ranking_measures(asked, ranked, asked.select("query_id", F.col("query_id").alias("id")), k)


def q_mrr20(spark, sf_dir):
    return _heldout(spark, sf_dir).select("queries", "mrr")


def q_top20(spark, sf_dir):
    return _heldout(spark, sf_dir).select("queries", "hit_rate")


def _retrieved(spark, sf_dir, items):
    """(item_id, context) from the fact passages, by hashed vectors."""
    facts = _facts(spark, sf_dir).persist(StorageLevel.DISK_ONLY)  # read for the vectors and for the contexts
    return qa.hashed_contexts(items, facts, FACT_DIMS, TOP)


def q_small(spark, sf_dir):
    items = _function(spark, sf_dir)
    return qa.answers(items, _retrieved(spark, sf_dir, items))


def q_large(spark, sf_dir):
    items = _function(spark, sf_dir)
    return qa.answers(items, _retrieved(spark, sf_dir, items), pairs.document_frequency(_facts(spark, sf_dir).withColumnRenamed("passage_id", "doc_id")))


def q_control(spark, sf_dir):
    return qa.answers(_function(spark, sf_dir), None)


def q_grid(spark, sf_dir):
    """Accuracy over benchmark x generator x retrieval: the answering table (stand-in generators)."""
    frequency = pairs.document_frequency(_facts(spark, sf_dir).withColumnRenamed("passage_id", "doc_id")).persist()
    rows = []
    for name, build in (("interaction", _interaction), ("function", _function)):
        items = build(spark, sf_dir).persist()
        for context_name, context in (("none", None), ("facts", _retrieved(spark, sf_dir, items))):
            for generator, weights in (("small", None), ("large", frequency)):
                rows.append(qa.accuracy(qa.answers(items, context, weights)).select(F.lit(name).alias("benchmark"), F.lit(context_name).alias("corpus"), F.lit(generator).alias("generator"), F.lit(True).alias("is_standin"), "*"))
    for name, build, in (("cloze", _cloze), ("yesno", _yesno), ("fulltext", _fulltext)):
        items = build(spark, sf_dir)
        rows.append(qa.accuracy(qa.answers(items, None)).select(F.lit(name).alias("benchmark"), F.lit("none").alias("corpus"), F.lit("small").alias("generator"), F.lit(True).alias("is_standin"), "*"))
    return reduce(lambda a, b: a.unionByName(b), rows)


def _training_pairs(spark, sf_dir):
    docs = _docs(spark, sf_dir)
    made = chunk.semantic_chunks(docs)
    asked = pairs.split_by_document(pairs.synth_questions(made, docs), docs).where("split = 'train'")
    return asked.select(F.col("chunk_id").alias("pair_id"), "chunk_id", "question").join(made.select("chunk_id", "text"), "chunk_id")


def q_fit(spark, sf_dir):
    """Loss by step of a hybrid run: 100 steps of 24 pairs on each of four workers."""
    _, log = train.fit_in_stage(_training_pairs(spark, sf_dir), train.TrainConfig())
    names = ("step", "pairs", "contrastive", "late", "loss")
    return spark.createDataFrame([tuple(r[n] for n in names) for r in log], "step int, pairs int, contrastive double, late double, loss double")


VARIANTS = {
    "hybrid-large-quantised": dict(spec=encode.EncoderSpec("large", True)), "hybrid-small": {}, "hybrid-small-no-gather": dict(gather=False),
    "contrastive-small": dict(loss="cl"), "late-small": dict(loss="li"), "hybrid-small-scaling": dict(adapter="ia3"),
}


def q_ablation(spark, sf_dir, steps=100):
    """P@10, MRR@10 on the graded set for tuned variants and the untuned base."""
    data = _training_pairs(spark, sf_dir).persist()
    out = []
    for name, more in [("untuned-small", None), *VARIANTS.items()]:
        cfg = train.TrainConfig(steps=steps, **(more or {}))
        adapter = None if more is None else train.fit_in_stage(data, cfg)[0]
        embed = lambda df, text, key, a=adapter, s=cfg.spec: encode.with_pooled(df, text, key, s, a)
        out.append(_measure_graded(10)(spark, sf_dir, embed).select(F.lit(name).alias("variant"), "*"))
    return reduce(lambda a, b: a.unionByName(b), out)


def q_registry(spark, sf_dir):
    """Warm and cold loading: tasks, loads and texts of each mode."""
    docs = _t(spark, sf_dir, "documents", "text").repartition(8)
    modes = [encode.registry_trace(docs, encode.EncoderSpec(), warm).select(F.lit(n).alias("mode"), "*") for n, warm in (("warm", True), ("cold", False))]
    return modes[0].unionByName(modes[1])


def graded_ctes() -> str:
    return f"""toks AS (SELECT item_id, {sql_tokens('text')} AS w FROM benchmark), n AS (SELECT count(*) AS items FROM benchmark),
g AS (SELECT item_id, w, unnest(range(0, 10)) AS grade, items FROM toks, n WHERE len(w) > 0),
p AS (SELECT g.*, o.w AS v, (SELECT list(p ORDER BY md5(g.item_id || '|' || g.grade || '|' || p)) FROM (SELECT unnest(range(0, len(g.w))) AS p)) AS places FROM g JOIN toks o ON o.item_id = (g.item_id + 1 + g.grade) % items),
graded AS (SELECT item_id AS question_id, 's' || (item_id % 20) AS subdomain, item_id * 10 + grade AS passage_id, grade::INT AS grade,
  array_to_string(list_transform(range(0, len(w)), lambda i: CASE WHEN list_contains(places[1 : (grade * len(w)) // 10], i) THEN v[(i % len(v)) + 1] ELSE w[i + 1] END), ' ') AS text FROM p)"""


def _rarest(size: int, rows: str = "benchmark", key: str = "item_id") -> str:
    return f"""bdf AS (SELECT token, count(*) AS df FROM (SELECT unnest(list_distinct({sql_tokens("coalesce(text, '')")})) AS token FROM documents) GROUP BY token),
bsp AS (SELECT {key}, token, min(place) AS place FROM (SELECT {key}, unnest(w) AS token, generate_subscripts(w, 1) AS place FROM (SELECT {key}, {sql_tokens('text')} AS w FROM {rows})) GROUP BY ALL),
brt AS (SELECT *, row_number() OVER (PARTITION BY {key} ORDER BY coalesce(df, 0), md5(token)) AS r FROM bsp LEFT JOIN bdf USING (token)),
rare AS (SELECT {key}, list(token ORDER BY place) AS words FROM brt WHERE r <= {size} GROUP BY {key})"""


def _dense(rows: str, key: str, text: str, dims: int) -> str:
    """(id, v): hashed counts as a list."""
    return f"""(SELECT id, list_transform(range(0, {dims}), lambda d: len(list_filter(codes, lambda c: c = d))::DOUBLE) AS v
  FROM (SELECT {key} AS id, list_transform({sql_tokens(text)}, lambda t: {sql_code('t')} % {dims}) AS codes FROM {rows}))"""


def _ranked(k: int) -> str:
    return f"""scored AS (SELECT q.id AS query_id, d.id, round(CASE WHEN q.n * d.n = 0 THEN 0 ELSE list_dot_product(q.v, d.v) / (q.n * d.n) END, 6) AS score
  FROM (SELECT *, sqrt(list_dot_product(v, v)) AS n FROM qv) q, (SELECT *, sqrt(list_dot_product(v, v)) AS n FROM dv) d),
ranked AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, id) AS rank FROM scored) WHERE rank <= {k})"""


def _choice(source: str) -> str:
    """item_id, question, options, answer_idx from (item_id, question, truth, wrong list)."""
    return f"""opts AS (SELECT item_id, question, truth, (SELECT list(o ORDER BY md5(item_id || '|' || o)) FROM (SELECT unnest(list_distinct(list_concat([truth], wrong))) AS o)) AS options FROM {source})
SELECT item_id, question, array_to_string(options, ' | ') AS options, (list_position(options, truth) - 1)::INT AS answer_idx FROM opts WHERE len(options) = 4"""


_edges = "edges AS (SELECT DISTINCT l_partkey AS entity, l_suppkey AS interactant FROM lineitem WHERE l_returnflag IN ('A', 'N', 'R'))"
_inter = f"""{_edges}, pool AS (SELECT interactant, row_number() OVER (ORDER BY interactant) - 1 AS at_no FROM (SELECT DISTINCT interactant FROM edges)),
ent AS (SELECT entity, arg_min(interactant, md5(entity || '-' || interactant)) AS truth FROM edges GROUP BY entity),
drawn AS (SELECT entity, at_no, min(d) AS n FROM (SELECT entity, d, {sql_code("entity || '-' || d")} % (SELECT count(*) FROM pool) AS at_no FROM ent, (SELECT unnest(range(1, {qa.DRAWS + 1})) AS d)) GROUP BY ALL),
frn AS (SELECT entity, interactant, row_number() OVER (PARTITION BY entity ORDER BY n) AS r FROM drawn JOIN pool USING (at_no) WHERE NOT EXISTS (SELECT 1 FROM edges e WHERE e.entity = drawn.entity AND e.interactant = pool.interactant)),
three AS (SELECT entity, list('supplier ' || interactant) AS wrong FROM frn WHERE r <= 3 GROUP BY entity HAVING count(*) = 3),
src AS (SELECT entity AS item_id, 'Which supplier provides part ' || entity || ' ' || p_name || '?' AS question, 'supplier ' || truth AS truth, wrong FROM ent JOIN three USING (entity) JOIN part ON p_partkey = entity)"""
_func = """kinds AS (SELECT DISTINCT p_type AS k FROM part WHERE p_type IS NOT NULL),
src AS (SELECT p_partkey AS item_id, 'What is the type of part ' || p_partkey || ' ' || p_name || '?' AS question, p_type AS truth,
  (SELECT list(k ORDER BY md5('w' || p_partkey || '|' || k)) FROM kinds WHERE k <> p_type)[1:3] AS wrong FROM part)"""
_fact = f"""{_edges}, facts AS (SELECT p_partkey AS passage_id, 'Part ' || p_partkey || ' ' || p_name || ' is of type ' || p_type || ' and comes from ' || known || '.' AS text
  FROM part JOIN (SELECT entity, string_agg('supplier ' || interactant, ', ' ORDER BY interactant) AS known FROM edges GROUP BY entity) ON entity = p_partkey)"""
_fitems = f"items AS (SELECT * FROM (WITH {_func}, {_choice('src')}))"


def _answer(context: str) -> str:
    """Answers of ``items`` with a context expression over ``seen``."""
    return f"""opt AS (SELECT item_id, answer_idx, {sql_tokens(context)} AS c, unnest(string_split(options, ' | ')) AS o, generate_subscripts(string_split(options, ' | '), 1) - 1 AS i FROM seen),
sc AS (SELECT item_id, answer_idx, i, len(list_intersect(list_distinct({sql_tokens('o')}), list_distinct(c))) AS score FROM opt),
ch AS (SELECT item_id, answer_idx, first(i ORDER BY score DESC, i)::INT AS chosen FROM sc GROUP BY item_id, answer_idx)
SELECT item_id, chosen, answer_idx, chosen = answer_idx AS correct FROM ch"""


_small = f"""WITH {_fact}, {_fitems}, dv AS {_dense('facts', 'passage_id', 'text', FACT_DIMS)}, qv AS {_dense('items', 'item_id', 'question', FACT_DIMS)}, {_ranked(TOP)},
ctx AS (SELECT query_id AS item_id, substr(string_agg(text, ' ' ORDER BY rank), 1, 4000) AS context FROM ranked JOIN facts ON passage_id = id GROUP BY query_id),
seen AS (SELECT items.*, coalesce(context, question) AS context FROM items LEFT JOIN ctx USING (item_id)), {_answer('context')}"""
_gq = f"{graded_ctes()}, {_rarest(8)}, gq AS (SELECT item_id AS query_id, array_to_string(words, ' ') AS question FROM rare)"


def _graded_measures(k: int) -> str:
    return f"""WITH {_gq}, dv AS {_dense('graded', 'passage_id', 'text', DIMS)}, qv AS {_dense('gq', 'query_id', 'question', DIMS)}, {_ranked(k)},
per AS (SELECT query_id, count(*) FILTER (id // 10 = query_id) AS found, min(rank) FILTER (id = query_id * 10) AS best FROM gq LEFT JOIN ranked USING (query_id) GROUP BY query_id)
SELECT count(*) AS queries, round(avg(found / {k}), 6) AS precision, round(avg(coalesce(1 / best, 0)), 6) AS mrr, round(avg((best IS NOT NULL)::INT), 6) AS hit_rate FROM per"""


_num = "(split_part(chunk_id, '-', 1)::BIGINT * 100000 + split_part(chunk_id, '-', 2)::BIGINT)"
_held = f"""WITH {QUESTIONS}, {_clusters}, tq AS (SELECT {_num} AS query_id, question FROM questions JOIN cl USING (doc_id) WHERE {_test('cluster_id')}), cn AS (SELECT {_num} AS cid, text FROM chunks),
dv AS {_dense('cn', 'cid', 'text', DIMS)}, qv AS {_dense('tq', 'query_id', 'question', DIMS)}, {_ranked(20)},
per AS (SELECT query_id, min(rank) FILTER (id = query_id) AS best FROM tq LEFT JOIN ranked USING (query_id) GROUP BY query_id)"""

def q_graded_precision(spark, sf_dir):
    return _measure_graded(10)(spark, sf_dir).select("queries", "precision")


def q_graded_mrr(spark, sf_dir):
    return _measure_graded(10)(spark, sf_dir).select("queries", "mrr")


QUERIES = {
    "graded_p10": q_graded_precision, "graded_mrr10": q_graded_mrr,
    "interaction_qa": _interaction, "function_qa": _function, "cloze_qa": _cloze, "yesno_qa": _yesno, "fulltext_qa": _fulltext, "fact_passages": _facts,
    "graded_set": _graded, "graded_questions": _graded_questions, "graded_validation": q_validate, "graded_p10_mrr10": _measure_graded(10), "graded_p20": _measure_graded(20),
    "heldout_mrr20": q_mrr20, "heldout_top20": q_top20, "rag_answers_small": q_small, "rag_answers_large": q_large, "no_retrieval_answers": q_control,
    "qa_accuracy_grid": q_grid, "fit_hybrid": q_fit, "fit_ablation_table": q_ablation, "registry_trace": q_registry,
}
ORACLES = {
    "graded_p10": f"SELECT queries, precision FROM ({_graded_measures(10)})", "graded_mrr10": f"SELECT queries, mrr FROM ({_graded_measures(10)})",
    "interaction_qa": f"WITH {_inter}, {_choice('src')}", "function_qa": f"WITH {_func}, {_choice('src')}", "fact_passages": f"WITH {_fact} SELECT passage_id, text FROM facts",
    "cloze_qa": f"""WITH {_rarest(1)}, k AS (SELECT item_id, words[1] AS word FROM rare),
src AS (SELECT b.item_id, array_to_string(list_transform({sql_tokens('text')}, lambda z: CASE WHEN z = word THEN '_' ELSE z END), ' ') AS question, word AS truth,
  (SELECT list(o.word) FROM k o WHERE o.item_id IN ((b.item_id + 1) % (SELECT count(*) FROM benchmark), (b.item_id + 2) % (SELECT count(*) FROM benchmark), (b.item_id + 3) % (SELECT count(*) FROM benchmark))) AS wrong
  FROM benchmark b JOIN k USING (item_id)), {_choice('src')}""",
    "yesno_qa": "SELECT doc_id AS item_id, 'Is document ' || doc_id || ' sound?' AS question, 'no | yes' AS options, quality AS answer_idx FROM labels SEMI JOIN documents USING (doc_id) WHERE quality IS NOT NULL",
    "fulltext_qa": rf"""WITH l AS (SELECT doc_id, lang, list_filter(regexp_split_to_array(substr(text, 1001), '[.!?]+\s+|\n+'), lambda x: regexp_matches(x, '\S'))[2] AS s FROM documents WHERE length(text) > 1000),
m AS (SELECT doc_id, s, [lead(s, 1) OVER w, lead(s, 2) OVER w, lead(s, 3) OVER w] AS wrong FROM l WHERE s IS NOT NULL WINDOW w AS (PARTITION BY lang ORDER BY doc_id)),
src AS (SELECT doc_id AS item_id, 'What does document ' || doc_id || ' say?' AS question, s AS truth, wrong FROM m WHERE len(list_filter(wrong, lambda x: x IS NULL)) = 0), {_choice('src')}""",
    "graded_set": f"WITH {graded_ctes()} SELECT question_id, subdomain, passage_id, grade, text FROM graded",
    "graded_questions": f"WITH {_gq} SELECT query_id, question FROM gq",
    "graded_validation": f"""WITH {_gq}, o AS (SELECT question_id, grade, len(list_intersect(list_distinct(string_split(question, ' ')), list_distinct({sql_tokens('text')}))) AS o FROM graded JOIN gq ON query_id = question_id),
l AS (SELECT question_id, coalesce(o <= lag(o) OVER (PARTITION BY question_id ORDER BY grade) + 1, true) AS ok FROM o), b AS (SELECT question_id, bool_and(ok) AS ordered FROM l GROUP BY question_id)
SELECT ordered, count(*) AS questions FROM b GROUP BY ordered""",
    "graded_p10_mrr10": _graded_measures(10), "graded_p20": _graded_measures(20),
    "heldout_mrr20": f"{_held} SELECT count(*) AS queries, round(avg(coalesce(1 / best, 0)), 6) AS mrr FROM per",
    "heldout_top20": f"{_held} SELECT count(*) AS queries, round(avg((best IS NOT NULL)::INT), 6) AS hit_rate FROM per",
    "rag_answers_small": _small,
    "no_retrieval_answers": f"WITH {_fitems}, seen AS (SELECT *, question AS context FROM items), {_answer('context')}",
}
