"""Queries on streams, costs and the flagship, with SQL of the equal batch results."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from litspark.catalog import load
from litspark.functions.text import sql_tokens
from litspark.operators import chunk, encode, index, parse
from litspark.plans import costs
from litspark.plans.q_index import K, _base, _cos, _queries, _rank, _vectors
from litspark.streaming import ingest


def _window(kind):
    return lambda spark, sf_dir: ingest.drained(ingest.windowed(ingest.stream(spark, sf_dir, "events"), kind), "complete")


def q_dedup(spark, sf_dir):
    return ingest.drained(ingest.deduplicated(ingest.stream(spark, sf_dir, "events")))


def q_ingest(spark, sf_dir):
    return ingest.drained(ingest.indexed_chunks(ingest.stream(spark, sf_dir, "pages")))


def q_static(spark, sf_dir):
    vectors = _vectors(spark, sf_dir)
    near = index.knn_gemm(_queries(vectors), vectors, 3).select("query_id", "rank", "id")
    return ingest.drained(ingest.query_log_topk(ingest.stream(spark, sf_dir, "events"), near))


def q_pairs(spark, sf_dir):
    kinds = sorted(r[0] for r in load(spark, sf_dir, "events", "event_type").distinct().collect())
    return ingest.drained(ingest.paired_events(ingest.stream(spark, sf_dir, "events"), kinds[0], kinds[-1]))


def q_flops(spark, sf_dir):
    return costs.flop_model(load(spark, sf_dir, "documents", "text"))


def q_normalised(spark, sf_dir):
    """Samples: pages with markup, documents with text, and questions asked in conversations."""
    tables = {"page": ("pages", F.length("html") > 0), "document": ("documents", F.length("text") > 0), "question": ("conversations", F.col("role") == "user")}
    counted = [load(spark, sf_dir, t).where(c).agg(F.count("*").alias("samples")).select(F.lit(kind).alias("kind"), "samples") for kind, (t, c) in tables.items()]
    return costs.normalised(spark, reduce(lambda a, b: a.unionByName(b), counted))


def q_scaling(spark, sf_dir):
    docs, pages = load(spark, sf_dir, "documents", "doc_id", "text"), load(spark, sf_dir, "pages")
    runs = [("chunk", chunk.semantic_chunks, docs), ("parse", parse.two_stage, pages), ("parse end-to-end", parse.parse_end_to_end, pages)]
    return reduce(lambda a, b: a.unionByName(b), [costs.scaling_curve(spark, f, t).select(F.lit(n).alias("stage"), "*") for n, f, t in runs])


def q_parser_throughput(spark, sf_dir):
    pages = load(spark, sf_dir, "pages").persist()
    n = pages.count()
    return costs.throughput(spark, {name: (lambda p=p: p(pages)) for name, p in parse.PARSERS.items()}, n, spark.sparkContext.defaultParallelism)


def flagship(spark, sf_dir):
    """Parse pages, cut them into semantic chunks, encode, and rank the five best for each benchmark text."""
    parsed = parse.two_stage(load(spark, sf_dir, "pages")).withColumn("doc_id", parse.doc_id(F.col("url"))).where("doc_id is not null")
    newest = parsed.groupBy("doc_id").agg(F.max_by("text", "page_id").alias("text"))
    made = chunk.semantic_chunks(newest).withColumn("id", F.col("doc_id") * 100_000 + F.col("chunk_no"))
    vectors = encode.hashed_vectors(made, "text", "id")
    questions = encode.hashed_vectors(load(spark, sf_dir, "benchmark"), "text", "item_id").select(F.col("id").alias("query_id"), "vector")
    return index.knn_gemm(questions, vectors, 5)


QUERIES = {
    "stream_tumbling": _window("tumbling"), "stream_sliding": _window("sliding"), "stream_session": _window("session"), "stream_dedup": q_dedup, "stream_index_ingest": q_ingest,
    "stream_static_topk": q_static, "stream_interval_join": q_pairs, "flop_model": q_flops, "normalised_rates": q_normalised, "strong_scaling": q_scaling, "parser_throughput": q_parser_throughput, "flagship_retrieval": flagship,
}
_ts = "strftime({0}, '%Y-%m-%d %H:%M:%S')"
_near = f"WITH {_base}, s AS (SELECT query_id, id, {_cos('qv', 'vector')} AS s FROM q, v), near AS (SELECT * FROM ({_rank('s', 3)}))"
_published = ", ".join(f"('{s}', '{m}', {w}, {r}::DOUBLE, {costs.NODES[s, m]}, '{costs.SAMPLES[s.split()[0]]}')" for s, m, w, r in costs.PUBLISHED)
ORACLES = {
    "normalised_rates": f"""WITH p(stage, machine, workers, rate, nodes, kind) AS (VALUES {_published}), s AS (SELECT 'page' AS kind, count(*) AS samples FROM pages WHERE length(html) > 0 UNION ALL SELECT 'document', count(*) FROM documents WHERE length(text) > 0 UNION ALL SELECT 'question', count(*) FROM conversations WHERE role = 'user')
SELECT stage, machine, workers::INT AS workers, rate, round(rate / workers, 6) AS per_worker, round(rate / nodes, 6) AS per_node, samples, round(samples / rate / 3600, 4) AS epoch_hours FROM p JOIN s USING (kind)""",
    "flop_model": f"""WITH n AS (SELECT len({sql_tokens("coalesce(text, '')")}) AS n FROM documents), c AS (SELECT n, (SELECT coalesce(min(8 * 4 ** k), 2147483647) FROM range(0, {costs.SIZE_CLASSES}) r(k) WHERE 8 * 4 ** k >= n)::INT AS tokens FROM n)
SELECT tokens, count(*) AS texts, count(*) * 128.0::DOUBLE AS pooled, sum(n)::DOUBLE * 1024 AS maxsim, sum(n)::DOUBLE * 1024 / (count(*) * 128) AS ratio FROM c GROUP BY tokens""",
    "stream_tumbling": f"SELECT {_ts.format('d')} AS start, {_ts.format('d + INTERVAL 1 DAY')} AS \"end\", event_type, n FROM (SELECT date_trunc('day', ts)::TIMESTAMP AS d, event_type, count(*) AS n FROM events GROUP BY ALL)",
    "stream_sliding": f"SELECT {_ts.format('d')} AS start, {_ts.format('d + INTERVAL 7 DAY')} AS \"end\", event_type, n FROM (SELECT date_trunc('day', ts)::TIMESTAMP - INTERVAL 1 DAY * i AS d, event_type, count(*) AS n FROM events, (SELECT unnest(range(0, 7)) AS i) GROUP BY ALL)",
    "stream_session": f"""WITH g AS (SELECT event_type, ts, CASE WHEN ts > lag(ts) OVER w + INTERVAL 7 DAY THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts)),
s AS (SELECT event_type, ts, sum(fresh) OVER (PARTITION BY event_type ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT {_ts.format('min(ts)')} AS start, {_ts.format('max(ts) + INTERVAL 7 DAY')} AS \"end\", event_type, count(*) AS n FROM s GROUP BY event_type, k""",
    "stream_dedup": f"SELECT DISTINCT user_id, event_type, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS hour FROM events",
    "stream_static_topk": f"{_near} SELECT event_id, query_id, rank, id FROM (SELECT event_id, (user_id % 10) * 50 AS query_id FROM events) JOIN near USING (query_id)",
    "stream_interval_join": "WITH k AS (SELECT min(event_type) AS a, max(event_type) AS b FROM events) SELECT x.event_id AS first_id, y.event_id AS second_id FROM events x, events y, k WHERE x.event_type = a AND y.event_type = b AND x.user_id = y.user_id AND y.ts >= x.ts AND y.ts <= x.ts + INTERVAL 1 DAY",
}
