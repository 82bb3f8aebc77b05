"""Queries on clusters, corpora, loading and baselines that have no SQL twin, and small ones that have."""

from __future__ import annotations

from functools import reduce

from pyspark import StorageLevel
from pyspark.sql import functions as F

from litspark.catalog import load
from litspark.operators import chunk, clusters, encode, index, qa
from litspark.plans.q_index import K, _queries, _vectors
from litspark.plans.q_qa import DIMS, _cloze, _fulltext, _measure_graded, q_registry


def kmeans_ivf(spark, sf_dir):
    vectors = _vectors(spark, sf_dir)
    cells = index.default_cells(vectors.count())
    seeds = clusters.kmeans_seeds(vectors, cells)
    return index.knn_ivf(_queries(vectors), index.build_ivf(vectors, seeds), seeds, K, index.default_probes(cells))


def cluster_quality(spark, sf_dir):
    """Purity of chunk vectors by language (well above chance) and of the given vectors by label (at chance)."""
    docs = load(spark, sf_dir, "documents", "doc_id", "text", "lang")
    texts = encode.hashed_vectors(docs, "text", "doc_id", DIMS).join(docs.select(F.col("doc_id").alias("id"), "lang"), "id")
    given = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vector"), F.col("label").cast("string").alias("lang"))
    rows = [clusters.purity(v, "lang", c).select(F.lit(n).alias("vectors"), "purity", "chance", "silhouette") for n, v, c in (("documents by language", texts, 8), ("embeddings by label", given, 10))]
    return rows[0].unionByName(rows[1])


def concept_graph(spark, sf_dir):
    docs = load(spark, sf_dir, "documents", "doc_id", "text", "source")
    vectors = encode.hashed_vectors(docs, "text", "doc_id", DIMS).join(docs.select(F.col("doc_id").alias("id"), "source"), "id")
    return clusters.concept_graph(vectors, vectors.where("id % 50 = 0").select(F.col("id").alias("query_id"), "vector", "source"), 3)


def qa_corpora(spark, sf_dir):
    """Accuracy of the small generator on cloze and full-text items: no retrieval, narrow corpus, broad corpus."""
    docs = load(spark, sf_dir, "documents", "doc_id", "text", "lang", "source")
    asked = {"cloze": _cloze(spark, sf_dir).persist(StorageLevel.DISK_ONLY), "fulltext": _fulltext(spark, sf_dir).persist(StorageLevel.DISK_ONLY)}  # read for each corpus
    rows = []
    for kind in (None, "narrow", "broad"):
        if kind:
            made = chunk.semantic_chunks(clusters.corpus(docs, kind)).withColumn("passage_id", F.col("doc_id") * 100_000 + F.col("chunk_no")).select("passage_id", "text").persist(StorageLevel.DISK_ONLY)
            vectors = encode.hashed_vectors(made, "text", "passage_id", DIMS)
        for name, items in asked.items():
            context = None
            if kind:
                queries = encode.hashed_vectors(items, "question", "item_id", DIMS).select(F.col("id").alias("query_id"), "vector")
                context = qa.found_contexts(items, queries, vectors, made, 5)
            rows.append(qa.accuracy(qa.answers(items, context)).select(F.lit(name).alias("benchmark"), F.lit(kind or "none").alias("corpus"), F.lit(True).alias("is_standin"), "*"))
    return reduce(lambda a, b: a.unionByName(b), rows)


def model_load_times(spark, sf_dir):
    return clusters.load_times(q_registry(spark, sf_dir))


def encoder_baselines(spark, sf_dir):
    """Graded-set measures of encoders without tuning: hashed counts, small and large base, and the base with domain weights."""
    docs = load(spark, sf_dir, "documents", "doc_id", "text", "lang", "source")
    idf = encode.fit_idf(clusters.corpus(docs, "narrow"))
    ways = {
        "hashed": None,
        "small base": lambda df, t, k: encode.with_pooled(df, t, k, encode.EncoderSpec("small")),
        "large base": lambda df, t, k: encode.with_pooled(df, t, k, encode.EncoderSpec("large")),
        "large base, 8 bit": lambda df, t, k: encode.with_pooled(df, t, k, encode.EncoderSpec("large", True)),
        "domain weights": lambda df, t, k: encode.with_pooled(df, t, k, encode.EncoderSpec("small"), idf=idf),
    }
    return reduce(lambda a, b: a.unionByName(b), [_measure_graded(10)(spark, sf_dir, e).select(F.lit(n).alias("encoder"), "*") for n, e in ways.items()])


def narrow_corpus(spark, sf_dir):
    return clusters.corpus(load(spark, sf_dir, "documents", "doc_id", "lang", "source"), "narrow")


def listagg(spark, sf_dir):
    o = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    return o.groupBy("o_custkey").agg(F.array_join(F.array_sort(F.collect_list("o_orderkey")), ",").alias("orders"))


def distinct_rows(spark, sf_dir):
    return load(spark, sf_dir, "lineitem", "l_returnflag", "l_linestatus").distinct()


def having(spark, sf_dir):
    return load(spark, sf_dir, "orders", "o_custkey", "o_totalprice").groupBy("o_custkey").agg(F.count("*").alias("n"), F.max("o_totalprice").alias("top")).where("n > 15")


def star_join(spark, sf_dir):
    """Three dimension tables around the fact table: revenue per region and year."""
    li = load(spark, sf_dir, "lineitem", "l_orderkey", "l_extendedprice")
    o = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    c = load(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    n, r = load(spark, sf_dir, "nation", "n_nationkey", "n_regionkey"), load(spark, sf_dir, "region")
    joined = li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    return joined.groupBy("r_name", F.year("o_orderdate").alias("y")).agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double").alias("revenue"))


QUERIES = {
    "kmeans_ivf": kmeans_ivf, "cluster_quality": cluster_quality, "concept_graph": concept_graph, "qa_corpora": qa_corpora, "model_load_times": model_load_times, "encoder_baselines": encoder_baselines,
    "narrow_corpus": narrow_corpus, "op_listagg": listagg, "op_distinct": distinct_rows, "op_having": having, "op_star_join": star_join,
}
ORACLES = {
    "narrow_corpus": "SELECT doc_id, lang, source FROM documents WHERE lang = 'en' AND source IN ('src0', 'src1', 'src2', 'src3', 'src4')",
    "op_listagg": "SELECT o_custkey, string_agg(o_orderkey::VARCHAR, ',' ORDER BY o_orderkey) AS orders FROM orders GROUP BY o_custkey",
    "op_distinct": "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem",
    "op_having": "SELECT o_custkey, count(*) AS n, max(o_totalprice) AS top FROM orders GROUP BY o_custkey HAVING count(*) > 15",
    "op_star_join": "SELECT r_name, year(o_orderdate)::INT AS y, sum(l_extendedprice::DECIMAL(18,2))::DOUBLE AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL",
}
