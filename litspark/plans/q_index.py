"""Queries on vector search and losses, with their SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from litspark.catalog import load
from litspark.operators import index, losses

K, DIMS, WIDTH = 10, 64, 8
CELLS, CAP = 23, 100
PROBES = index.default_probes(CELLS)


def _vectors(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vector"))


def _queries(vectors):
    """The stated query set: ids divisible by 50."""
    return vectors.where("id % 50 = 0").select(F.col("id").alias("query_id"), "vector")


def _search(function, **more):
    def query(spark, sf_dir):
        vectors = _vectors(spark, sf_dir)
        return function(_queries(vectors), vectors, K, **more)

    return query


def _ivf(spark, sf_dir):
    vectors = _vectors(spark, sf_dir)
    seeds = vectors.where(F.col("id") < CELLS).select(F.col("id").alias("cell"), F.col("vector").alias("seed"))
    return index.knn_ivf(_queries(vectors), index.build_ivf(vectors, seeds), seeds, K, PROBES)


def _int8(spark, sf_dir):
    """Codes as a store would hold them: the scan reads them alone."""
    vectors = _vectors(spark, sf_dir)
    return index.knn_int8(_queries(vectors), index.codes_of(vectors).persist(), vectors, K)


def _recall(spark, sf_dir):
    vectors = _vectors(spark, sf_dir)
    truth = index.knn_gemm(_queries(vectors), vectors, K)
    ways = {"int8": _int8(spark, sf_dir), "ivf": _ivf(spark, sf_dir), "lsh": index.knn_lsh(_queries(vectors), vectors, K, DIMS)}
    out = None
    for name, found in ways.items():
        row = index.recall(found, truth).select(F.lit(name).alias("method"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def _rerank(spark, sf_dir):
    vectors = _vectors(spark, sf_dir)
    queries = _queries(vectors)
    return index.maxsim_rerank(queries, vectors, index.knn_gemm(queries, vectors, 4 * K), K, WIDTH)


def _full(spark, sf_dir):
    vectors = _vectors(spark, sf_dir)
    return index.maxsim_full(_queries(vectors), vectors, K, WIDTH)


def _batch(spark, sf_dir):
    v = _vectors(spark, sf_dir)
    docs = v.select((F.col("id") - 1).alias("id"), F.col("vector").alias("document"))
    return v.where("id % 2 = 0").join(docs, "id").select(F.pmod(F.floor(F.col("id") / 2), F.lit(4)).cast("int").alias("rank"), F.col("id").alias("pos"), F.col("vector").alias("query"), "document")


def _maxsim_pairs(spark, sf_dir):
    """Late interaction of each question with its own document."""
    score = index.maxsim_column(index.token_matrix(F.col("query"), WIDTH), index.token_matrix(F.col("document"), WIDTH))
    return _batch(spark, sf_dir).select("pos", F.round(score, 6).alias("maxsim"))


def _loss(function, **more):
    def query(spark, sf_dir):
        out = function(_batch(spark, sf_dir), **more)
        return out.select(*[F.round(c, 4).alias(c) if t == "double" else c for c, t in out.dtypes])

    return query


def _pair_cost(spark, sf_dir):
    """Comparisons of token-level and pooled similarity of each question with each benchmark text."""
    from litspark.functions.text import token_array

    n = load(spark, sf_dir, "benchmark").select("item_id", F.size(token_array(F.col("text"))).cast("long").alias("n"))
    # sums over the items behind each one, in place of a row for every pair
    behind = Window.partitionBy(F.lit(0)).orderBy(F.desc("item_id")).rangeBetween(Window.unboundedPreceding, Window.currentRow)
    whole = n.groupBy("item_id").agg(F.sum("n").alias("n"), F.count("*").alias("c"))  # the items are a stated, small set
    later = whole.select("item_id", "n", (F.sum("n").over(behind) - F.col("n")).alias("m"), (F.sum("c").over(behind) - F.col("c")).alias("p"), "c").where("p > 0")
    return later.select("item_id", (F.col("n") * F.col("m")).alias("token_pairs"), (F.col("c") * F.col("p")).alias("pooled_pairs"))


def _purity(spark, sf_dir):
    """Label agreement of the ten nearest neighbours, overall: at chance on these vectors."""
    vectors = _vectors(spark, sf_dir)
    labels = load(spark, sf_dir, "embeddings", "vec_id", "label")
    near = index.knn_gemm(_queries(vectors), vectors, K + 1).where("query_id <> id")
    own = labels.select(F.col("vec_id").alias("query_id"), F.col("label").alias("own"))
    found = near.join(labels.withColumnRenamed("vec_id", "id"), "id").join(own, "query_id")
    return found.agg(F.count("*").alias("neighbours"), F.sum((F.col("label") == F.col("own")).cast("long")).alias("agree"))


def _dot(a: str, b: str) -> str:
    return f"list_sum(list_transform(range(1, len({a}) + 1), lambda i: {a}[i]::DOUBLE * {b}[i]::DOUBLE))"


def _cos(a: str, b: str) -> str:
    return f"({_dot(a, b)} / (sqrt({_dot(a, a)}) * sqrt({_dot(b, b)})))"


_base = "v AS (SELECT vec_id AS id, embedding AS vector FROM embeddings), q AS (SELECT id AS query_id, vector AS qv FROM v WHERE id % 50 = 0)"


def _rank(scored: str, k: int = K) -> str:
    return f"SELECT query_id, rank::INT AS rank, id, score FROM (SELECT query_id, id, score, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, id) AS rank FROM (SELECT query_id, id, round(s, 6) AS score FROM {scored})) WHERE rank <= {k}"


_exact = f"WITH {_base}, s AS (SELECT query_id, id, {_cos('qv', 'vector')} AS s FROM q, v) {_rank('s')}"
_seeds = f"seeds AS (SELECT id AS cell, vector AS seed FROM v WHERE id < {CELLS})"
_ivf_ctes = f"""{_base}, {_seeds},
owned AS (SELECT id, vector, cell FROM (SELECT id, vector, cell, row_number() OVER (PARTITION BY id ORDER BY round({_cos('vector', 'seed')}, 9) DESC, cell) AS r FROM v, seeds) WHERE r = 1),
probes AS (SELECT query_id, qv, cell FROM (SELECT query_id, qv, cell, row_number() OVER (PARTITION BY query_id ORDER BY round({_cos('qv', 'seed')}, 9) DESC, cell) AS r FROM q, seeds) WHERE r <= {PROBES}),
s AS (SELECT query_id, id, {_cos('qv', 'vector')} AS s FROM probes JOIN owned USING (cell))"""
_sign = "(CASE WHEN ('0x' || substr(md5(b || '-' || (d - 1)), 1, 1))::INT < 8 THEN 1.0 ELSE -1.0 END)"
_lsh_ctes = f"""{_base},
sides AS (SELECT id, b, (list_sum(list_transform(range(1, {DIMS + 1}), lambda d: vector[d]::DOUBLE * {_sign})) > 0)::INT AS side FROM v, (SELECT unnest(range(64)) AS b)),
bands AS (SELECT id, b // 4 AS band, string_agg(side::VARCHAR, '' ORDER BY b) AS sides FROM sides GROUP BY id, b // 4),
met AS (SELECT DISTINCT x.id AS query_id, y.id FROM bands x JOIN bands y USING (band, sides) WHERE x.id % 50 = 0),
s AS (SELECT query_id, v.id, {_cos('qv', 'vector')} AS s FROM met JOIN q USING (query_id) JOIN v ON v.id = met.id)"""
_tok = lambda v: f"list_transform(range(0, {DIMS // WIDTH}), lambda t: {v}[t * {WIDTH} + 1 : t * {WIDTH} + {WIDTH}])"
_maxsim = lambda a, b: f"list_sum(list_transform({_tok(a)}, lambda x: list_max(list_transform({_tok(b)}, lambda y: {_cos('x', 'y')}))))"
_top = f"first AS (SELECT * FROM ({_rank('s', 4 * K)}))"
_loss_base = """v AS (SELECT vec_id AS id, embedding AS vector FROM embeddings),
batch AS (SELECT ((a.id // 2) % 4)::INT AS rank, a.id AS pos, a.vector AS q, b.vector AS d FROM v a JOIN v b ON b.id = a.id + 1 WHERE a.id % 2 = 0)"""


def _cands(gather: bool, cap: int | None) -> str:
    if not gather:
        return "cands AS (SELECT rank, rank AS c_rank, pos AS c_pos, d FROM batch)"
    limit = f"WHERE n <= greatest({cap}, local)" if cap else ""
    return f"""ranks AS (SELECT rank, count(*) AS local FROM batch GROUP BY rank),
cands AS (SELECT * FROM (SELECT r.rank, r.local, b.rank AS c_rank, b.pos AS c_pos, d, row_number() OVER (PARTITION BY r.rank ORDER BY (b.rank <> r.rank)::INT, b.rank, b.pos) AS n FROM ranks r, batch b) {limit})"""


def _entropy(name: str) -> str:
    return f"""{name}_m AS (SELECT *, max(s) OVER (PARTITION BY rank, pos) AS m FROM {name}_s),
{name} AS (SELECT rank, avg(loss) AS loss, count(*) AS pairs FROM (SELECT rank, pos, ln(sum(exp(s - m))) + max(m) - max(s) FILTER (own) AS loss FROM {name}_m GROUP BY rank, pos) GROUP BY rank)"""


def _cl(gather: bool, cap: int | None = None) -> str:
    return f"""{_loss_base}, {_cands(gather, cap)},
cl_s AS (SELECT b.rank, b.pos, c_rank = b.rank AND c_pos = b.pos AS own, {_cos('b.q', 'c.d')} / {losses.TAU} AS s FROM batch b JOIN cands c ON c.rank = b.rank), {_entropy('cl')}"""


_li = f"""li_s AS (SELECT b.rank, b.pos, c.pos = b.pos AS own, {_maxsim('b.q', 'c.d')} / ({DIMS // WIDTH} * {losses.TAU}) AS s FROM batch b JOIN batch c ON c.rank = b.rank), {_entropy('li')}"""

QUERIES = {
    "knn_cosine_exact": _search(index.knn_nested),
    "knn_euclidean_exact": _search(index.knn_nested, metric="euclidean"),
    "knn_gemm": _search(index.knn_gemm),
    "knn_gemm_euclidean": _search(index.knn_gemm, metric="euclidean"),
    "knn_int8_rescored": _int8,
    "knn_ivf": _ivf,
    "knn_lsh": _search(index.knn_lsh, dims=DIMS),
    "ann_recall": _recall,
    "late_interaction_rerank": _rerank,
    "maxsim_full_small": _full,
    "maxsim_pairs": _maxsim_pairs,
    "embedding_label_agreement": _purity,
    "contrastive_loss_local": _loss(losses.contrastive, gather=False),
    "contrastive_loss_gathered": _loss(losses.contrastive),
    "contrastive_loss_capped": _loss(losses.contrastive, cap=CAP),
    "late_interaction_loss": _loss(losses.late_interaction, width=WIDTH),
    "hybrid_loss": _loss(losses.hybrid, width=WIDTH, cap=CAP),
    "pair_cost": _pair_cost,
}
_neg = "-sqrt(list_sum(list_transform(range(1, len(qv) + 1), lambda i: (qv[i]::DOUBLE - vector[i]::DOUBLE) ** 2)))"
_euclid = f"WITH {_base}, s AS (SELECT query_id, id, {_neg} AS s FROM q, v) {_rank('s')}"
_tokens = r"len(list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda y: y <> ''))"
ORACLES = {
    "knn_cosine_exact": _exact, "knn_gemm": _exact, "knn_int8_rescored": _exact, "knn_euclidean_exact": _euclid, "knn_gemm_euclidean": _euclid,
    "knn_ivf": f"WITH {_ivf_ctes} {_rank('s')}",
    "knn_lsh": f"WITH {_lsh_ctes} {_rank('s')}",
    "late_interaction_rerank": f"WITH {_base}, s AS (SELECT query_id, id, {_cos('qv', 'vector')} AS s FROM q, v), {_top}, t AS (SELECT f.query_id, f.id, {_maxsim('qv', 'vector')} AS s FROM first f JOIN q USING (query_id) JOIN v ON v.id = f.id) {_rank('t')}",
    "maxsim_pairs": f"WITH {_loss_base} SELECT pos, round({_maxsim('q', 'd')}, 6) AS maxsim FROM batch",
    "maxsim_full_small": f"WITH {_base}, s AS (SELECT query_id, id, {_maxsim('qv', 'vector')} AS s FROM q, v) {_rank('s')}",
    "embedding_label_agreement": f"WITH {_base}, s AS (SELECT query_id, id, {_cos('qv', 'vector')} AS s FROM q, v), n AS (SELECT * FROM ({_rank('s', K + 1)}) WHERE query_id <> id) SELECT count(*) AS neighbours, sum((a.label = b.label)::INT)::BIGINT AS agree FROM n JOIN embeddings a ON a.vec_id = n.id JOIN embeddings b ON b.vec_id = n.query_id",
    "contrastive_loss_local": f"WITH {_cl(False)} SELECT rank, round(loss, 4) AS loss, pairs FROM cl",
    "contrastive_loss_gathered": f"WITH {_cl(True)} SELECT rank, round(loss, 4) AS loss, pairs FROM cl",
    "contrastive_loss_capped": f"WITH {_cl(True, CAP)} SELECT rank, round(loss, 4) AS loss, pairs FROM cl",
    "late_interaction_loss": f"WITH {_loss_base}, {_li} SELECT rank, round(loss, 4) AS loss, pairs FROM li",
    "hybrid_loss": f"WITH {_cl(True, CAP)}, {_li} SELECT rank, round(cl.loss, 4) AS contrastive, round(li.loss, 4) AS late, round((cl.loss + li.loss) / 2, 4) AS loss FROM cl JOIN li USING (rank)",
    "pair_cost": f"WITH n AS (SELECT item_id, {_tokens} AS n FROM benchmark) SELECT a.item_id, sum(a.n * b.n)::BIGINT AS token_pairs, count(*) AS pooled_pairs FROM n a JOIN n b ON a.item_id < b.item_id GROUP BY a.item_id",
}
