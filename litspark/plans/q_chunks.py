"""Queries on sentences, chunks, question pairs and splits, with their SQL."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import functions as F

from litspark.catalog import load
from litspark.functions.text import DIMS, SQL_SENTENCES, hash_code, sentences, sparse_features, sql_code, sql_features, sql_tokens, token_array
from litspark.operators import chunk, pairs


def _docs(spark, sf_dir, *columns):
    return load(spark, sf_dir, "documents", *(columns or ("doc_id", "text")))


def q_sentences(spark, sf_dir):
    return sentences(_docs(spark, sf_dir))


def q_tokens(spark, sf_dir):
    spread = _docs(spark, sf_dir).select("doc_id", F.posexplode(token_array(F.coalesce("text", F.lit("")))).alias("at", "token"))
    return spread.groupBy("token").agg(F.count("*").alias("n"), F.count_distinct("doc_id").alias("df")).withColumn("code", hash_code(F.col("token")))


def q_features(spark, sf_dir):
    return sparse_features(_docs(spark, sf_dir), ["doc_id"], "text")


def q_adjacent(spark, sf_dir):
    size = F.sqrt(F.col("n1") * F.col("n2"))
    return chunk.adjacent_similarity(_docs(spark, sf_dir)).where("sent_no > 0").select("doc_id", "sent_no", "dot", "n1", "n2", F.round(F.when(size > 0, F.col("dot") / size).otherwise(0.0), 6).alias("cosine"))


def _chunks(threshold, windowed):
    def query(spark, sf_dir):
        return (chunk.semantic_chunks_windowed if windowed else chunk.semantic_chunks)(_docs(spark, sf_dir), threshold)

    return query


def _variant(**more):
    return lambda spark, sf_dir: chunk.semantic_chunks(_docs(spark, sf_dir), **more)


def q_running_mean(spark, sf_dir):
    """How chunk counts move with the threshold: chunks per threshold, from one pass over similarities."""
    near = chunk.adjacent_similarity(_docs(spark, sf_dir))
    grid = F.explode(F.array(*[F.struct(F.lit(n).alias("num"), F.lit(10).alias("den")) for n in (1, 2, 3, 5, 7)])).alias("t")
    both = near.select("sent_no", "dot", "n1", "n2", grid)
    fresh = (F.col("sent_no") == 0) | (F.col("n1") * F.col("n2") == 0) | (F.col("dot") * F.col("dot") * F.col("t.den") * F.col("t.den") < F.col("n1") * F.col("n2") * F.col("t.num") * F.col("t.num"))
    return both.groupBy((F.col("t.num") / F.col("t.den")).alias("threshold")).agg(F.sum(fresh.cast("long")).alias("chunks"))


def q_fixed(spark, sf_dir):
    return chunk.fixed_chunks(_docs(spark, sf_dir))


def _granular(name):
    return lambda spark, sf_dir: chunk.granularity_chunks(_docs(spark, sf_dir), name)


def _questions(spark, sf_dir):
    docs = _docs(spark, sf_dir, "doc_id", "text", "lang")
    return pairs.synth_questions(chunk.semantic_chunks(docs), docs)


def q_composition(spark, sf_dir):
    docs = _docs(spark, sf_dir, "doc_id", "text", "lang", "source")
    made = chunk.semantic_chunks(docs)
    return pairs.composition(docs, made, pairs.synth_questions(made, docs))


def q_subdomains(spark, sf_dir):
    return pairs.subdomain_distribution(_docs(spark, sf_dir, "source", "lang"))


def q_heldout(spark, sf_dir):
    docs = _docs(spark, sf_dir, "doc_id", "text", "lang")
    return pairs.split_by_document(_questions(spark, sf_dir), docs).select("chunk_id", "doc_id", "cluster_id", "split")


def q_leakage(spark, sf_dir):
    docs, asked = _docs(spark, sf_dir), _questions(spark, sf_dir).select("chunk_id", "doc_id")
    rows = [pairs.leakage(f(asked, docs)).select(F.lit(n).alias("split"), "*") for n, f in (("document", pairs.split_by_document), ("pair", pairs.split_by_pair))]
    return rows[0].unionByName(rows[1])


NEAR = f"""{SQL_SENTENCES},
feat AS {sql_features('sent', 'doc_id, sent_no', 'sentence', DIMS)},
sizes AS (SELECT doc_id, sent_no, sum(w * w)::BIGINT AS n FROM feat GROUP BY ALL),
dots AS (SELECT b.doc_id, b.sent_no, sum(a.w * b.w)::BIGINT AS dot FROM feat a JOIN feat b ON a.doc_id = b.doc_id AND a.sent_no + 1 = b.sent_no AND a.dim = b.dim GROUP BY ALL),
near AS (SELECT sent.doc_id, sent.sent_no, sentence, coalesce(dot, 0) AS dot, coalesce(lag(n) OVER (PARTITION BY sent.doc_id ORDER BY sent.sent_no), 0) AS n1, coalesce(n, 0) AS n2
  FROM sent LEFT JOIN sizes USING (doc_id, sent_no) LEFT JOIN dots USING (doc_id, sent_no))"""


def chunk_ctes(num: int = 1, den: int = 10) -> str:
    return f"""{NEAR},
marked AS (SELECT *, (sum(CASE WHEN sent_no > 0 AND n1 * n2 > 0 AND dot * dot * {den * den} >= n1 * n2 * {num * num} THEN 0 ELSE 1 END) OVER (PARTITION BY doc_id ORDER BY sent_no) - 1)::INT AS chunk_no FROM near),
chunks AS (SELECT doc_id || '-' || chunk_no AS chunk_id, doc_id, chunk_no, min(sent_no)::INT AS sent_from, max(sent_no)::INT AS sent_to,
  string_agg(sentence, '. ' ORDER BY sent_no) AS text, sum(len({sql_tokens('sentence')}))::INT AS n_tokens FROM marked GROUP BY doc_id, chunk_no)"""


_frames = "CASE lang " + " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in pairs.FRAMES.items()) + " ELSE 'What about' END"
QUESTIONS = f"""{chunk_ctes()},
df AS (SELECT token, count(*) AS df FROM (SELECT unnest(list_distinct({sql_tokens("coalesce(text, '')")})) AS token FROM documents) GROUP BY token),
toks AS (SELECT chunk_id, doc_id, {sql_tokens('text')} AS w FROM chunks),
spread AS (SELECT chunk_id, doc_id, token, min(at) AS at FROM (SELECT chunk_id, doc_id, unnest(w) AS token, generate_subscripts(w, 1) AS at FROM toks WHERE len(list_distinct(w)) >= {pairs.ACCEPT_TOKENS}) GROUP BY ALL),
rated AS (SELECT *, row_number() OVER (PARTITION BY chunk_id ORDER BY df, md5(token)) AS r FROM spread JOIN df USING (token)),
asked AS (SELECT chunk_id, doc_id, string_agg(token, ' ' ORDER BY at) AS words FROM rated WHERE r <= {pairs.QUESTION_TOKENS} GROUP BY chunk_id, doc_id),
questions AS (SELECT chunk_id, doc_id, {_frames} || ' ' || words || ' ?' AS question FROM asked JOIN documents USING (doc_id))""".replace(" at,", " place,").replace("min(at) AS at", "min(place) AS place").replace("AS at FROM", "AS place FROM").replace("ORDER BY at)", "ORDER BY place)")
_clusters = "cl AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS cluster_id FROM documents)"


def _test(key: str) -> str:
    return f"{sql_code(f'({key})::VARCHAR')} % 100 < {pairs.HELD_OUT_PERCENT}"


_step = 96
QUERIES = {
    "sentences": q_sentences,
    "semantic_chunks_bounded": _variant(max_tokens=64),
    "semantic_chunks_centroid": _variant(centroid=True),
    "tokens": q_tokens,
    "hash_features_sparse": q_features,
    "adjacent_cosine": q_adjacent,
    "semantic_chunks_t10": _chunks(Fraction(1, 10), True),
    "semantic_chunks_t20": _chunks(Fraction(1, 5), True),
    "semantic_chunks_inrow": _chunks(Fraction(1, 10), False),
    "semantic_chunks_inrow_t20": _chunks(Fraction(1, 5), False),
    "chunk_threshold_sweep": q_running_mean,
    "fixed_chunks": q_fixed,
    "paragraph_chunks": _granular("paragraph"),
    "sentence_chunks": _granular("sentence"),
    "document_chunks": _granular("document"),
    "synthetic_questions": _questions,
    "corpus_composition": q_composition,
    "subdomain_distribution": q_subdomains,
    "heldout_split": q_heldout,
    "leaky_split_overlap": q_leakage,
}
_cols = "chunk_id, doc_id, chunk_no, sent_from, sent_to, text, n_tokens"
ORACLES = {
    "sentences": f"WITH {SQL_SENTENCES} SELECT doc_id, sent_no, sentence FROM sent",
    "tokens": f"WITH t AS (SELECT doc_id, unnest({sql_tokens("text")}) AS token FROM documents) SELECT token, count(*) AS n, count(DISTINCT doc_id) AS df, {sql_code('token')} AS code FROM t GROUP BY token",
    "hash_features_sparse": f"SELECT doc_id, dim, w FROM {sql_features('documents', 'doc_id', 'text')}",
    "adjacent_cosine": f"WITH {NEAR} SELECT doc_id, sent_no, dot, n1, n2, round(CASE WHEN n1 * n2 > 0 THEN dot / sqrt(n1 * n2) ELSE 0 END, 6)::DOUBLE AS cosine FROM near WHERE sent_no > 0",
    "semantic_chunks_t10": f"WITH {chunk_ctes(1, 10)} SELECT {_cols} FROM chunks",
    "semantic_chunks_t20": f"WITH {chunk_ctes(1, 5)} SELECT {_cols} FROM chunks",
    "semantic_chunks_inrow": f"WITH {chunk_ctes(1, 10)} SELECT {_cols} FROM chunks",
    "semantic_chunks_inrow_t20": f"WITH {chunk_ctes(1, 5)} SELECT {_cols} FROM chunks",
    "chunk_threshold_sweep": f"WITH {NEAR}, grid(num) AS (VALUES (1), (2), (3), (5), (7)) SELECT num / 10 AS threshold, count(*) FILTER (sent_no = 0 OR n1 * n2 = 0 OR dot * dot * 100 < n1 * n2 * num * num) AS chunks FROM near, grid GROUP BY num",
    "fixed_chunks": f"""WITH w AS (SELECT doc_id, {sql_tokens("coalesce(text, '')")} AS w FROM documents),
s AS (SELECT doc_id, w, unnest(range(0, greatest(ceil((len(w) - 32) / {_step})::INT, 1)))::INT AS chunk_no FROM w WHERE len(w) > 0)
SELECT doc_id, chunk_no, len(w[chunk_no * {_step} + 1 : chunk_no * {_step} + 128])::INT AS n_tokens, array_to_string(w[chunk_no * {_step} + 1 : chunk_no * {_step} + 128], ' ') AS text FROM s""",
    "paragraph_chunks": r"WITH p AS (SELECT doc_id, list_filter(regexp_split_to_array(text, '\n+'), lambda x: regexp_matches(x, '\S')) AS s FROM documents) SELECT doc_id, (generate_subscripts(s, 1) - 1)::INT AS chunk_no, unnest(s) AS text FROM p",
    "sentence_chunks": f"WITH {SQL_SENTENCES} SELECT doc_id, sent_no AS chunk_no, sentence AS text FROM sent",
    "document_chunks": r"SELECT doc_id, 0 AS chunk_no, text FROM documents WHERE regexp_matches(text, '\S')",
    "synthetic_questions": f"WITH {QUESTIONS} SELECT chunk_id, doc_id, question FROM questions",
    "corpus_composition": f"""WITH {QUESTIONS},
per AS (SELECT source, (SELECT count(*) FROM chunks c WHERE c.doc_id = d.doc_id) AS c, (SELECT count(*) FROM questions q WHERE q.doc_id = d.doc_id) AS q FROM documents d)
SELECT CASE WHEN grouping(source) = 1 THEN 'Total' ELSE source END AS source, count(*) AS documents, sum(c)::BIGINT AS chunks, sum(q)::BIGINT AS questions FROM per GROUP BY ROLLUP (source)""",
    "subdomain_distribution": "SELECT source, lang, count(*) AS documents, round(count(*) / sum(count(*)) OVER (PARTITION BY source), 6) AS share FROM documents GROUP BY source, lang",
    "heldout_split": f"WITH {QUESTIONS}, {_clusters} SELECT chunk_id, doc_id, cluster_id, CASE WHEN {_test('cluster_id')} THEN 'test' ELSE 'train' END AS split FROM questions JOIN cl USING (doc_id)",
    "leaky_split_overlap": f"""WITH {QUESTIONS}, {_clusters},
d AS (SELECT 'document' AS split, cluster_id, {_test('cluster_id')} AS t FROM questions JOIN cl USING (doc_id) UNION ALL SELECT 'pair', cluster_id, {_test('chunk_id')} FROM questions JOIN cl USING (doc_id)),
seen AS (SELECT DISTINCT split, cluster_id FROM d WHERE NOT t)
SELECT split, count(*) AS test_pairs, count(*) FILTER (EXISTS (SELECT 1 FROM seen s WHERE s.split = d.split AND s.cluster_id = d.cluster_id)) AS leaked_pairs FROM d WHERE t GROUP BY split""",
}
