"""Methods against hand-made cases: parsing, chunking, measures, losses, training, registry, search, streams."""

from __future__ import annotations

import math
from fractions import Fraction

import numpy as np
import pytest
from conftest import same_rows
from pyspark.sql import functions as F

from litspark.functions import measures
from litspark.functions.text import split_sentences
from litspark.functions.vectors import maxsim, unit
from litspark.operators import chunk, encode, index, losses, parse, qa, relational, train
from litspark.operators.registry import Registry
from litspark.plans import costs, q_ops
from litspark.streaming import ingest

PAGE = """<html><head><title>t</title><script>var a="</p>";</script></head><body><nav><ul><li>menu</li></ul></nav><div class="ad">buy</div>
<article><h1>Title</h1><div class="author">A. B.</div><time>2020</time><div class="abstract">Short.</div><div class="keywords">k1, k2</div>
<h2>Part</h2><p>One &amp; <b>two</b><p>Three<ul><li>item</li></ul><table><tr><td>a</td><td>b</td></tr></table><figure><img src="x"><figcaption>Cap</figcaption></figure>
<math>x=1</math><pre>code()</pre><div class="footnote">note</div><div class="references">ref</div><div class="citation">cite</div></article><footer>foot</footer></body></html>"""


def test_regions_cover_the_kinds():
    found = parse.regions(PAGE)
    kinds = {r[1] for r in found}
    assert kinds >= {"header_nav", "advert", "title", "author", "date", "abstract", "keywords", "heading", "paragraph", "list_item", "table", "figure", "caption", "equation", "code", "footnote", "reference", "citation", "footer"}
    assert len(parse.KINDS) == 20
    assert [r[3] for r in found if r[1] == "paragraph"] == ["One & two", "Three"]
    skipped = parse.regions(PAGE, frozenset({"paragraph"}))
    assert all((r[3] is not None) == (r[1] == "paragraph") for r in skipped)
    assert parse.regions(None) == [] and parse.regions("") == []


#: A title that was cut inside a reference, as in the given pages; references without a semicolon are text.
CUT = "<body><article><h1>Bread &amp; salt &amp</h1><p>a &ampb; &notit; &lt;c&gt; &#233;&copy &quot;</p></article></body>"
CUT_TITLE, CUT_TEXT = "Bread & salt &amp", 'a &ampb; &notit; <c> é&copy "'


def test_regions_decode_whole_references_only():
    assert [r[3] for r in parse.regions(CUT)] == [CUT_TITLE, CUT_TEXT]


def test_the_tree_decodes_whole_references_only():
    assert parse.end_to_end_text(CUT) == f"{CUT_TITLE} {CUT_TEXT}"
    assert [parse.region_text(CUT[r[4] : r[5]]) for r in parse.regions(CUT)] == [CUT_TITLE, CUT_TEXT]
    assert parse.end_to_end_text("<article><p>\ue000 &amp;<script>a &amp;& b</script></article>") == "\ue000 & a &amp;& b"


def test_scanline_decodes_whole_references_only():
    assert parse.scanline_text(CUT) == f"{CUT_TITLE} {CUT_TEXT}"


def test_composed_stages_equal_the_fused_pass(spark):
    pages = spark.createDataFrame([(1, "http://a.b/en/7", PAGE), (2, "http://a.b/en/7", "<article></article>"), (3, None, None)], "page_id long, url string, html string")
    staged = parse.pipeline(lambda p: parse.detect_layout(p, parse.TEXT_KINDS), parse.assemble)(pages)
    fused = parse.two_stage(pages).where("text <> ''")
    assert staged.select("page_id", "text").collect() == fused.select("page_id", "text").collect()
    assert [r.route for r in pages.select(parse.route(F.col("html")).alias("route")).collect()] == ["extract", "recognise", "recognise"]


def test_chunk_edges():
    assert chunk.cut([]) == []
    assert chunk.cut(["one two"]) == [(0, 0, 2)]
    assert [c[:2] for c in chunk.cut(["a b", "...", "a b"])] == [(0, 0), (1, 1), (2, 2)]
    # cosine exactly 1/2: joins at the threshold, breaks just above it
    assert chunk.joins(1, 2, 2, Fraction(1, 2)) and not chunk.joins(1, 2, 2, Fraction(51, 100))
    assert not chunk.joins(0, 0, 3, Fraction(1, 10))


def test_chunks_keep_all_sentences_and_grow_with_the_threshold(spark, sf):
    text = "One two three. Two three four! Five six?\nSeven."
    said = split_sentences(text)
    counts = []
    for t in (Fraction(1, 10), Fraction(1, 2), Fraction(99, 100)):
        spans = chunk.cut(said, t)
        assert [i for a, b, _ in spans for i in range(a, b + 1)] == list(range(len(said)))
        counts.append(len(spans))
    assert counts == sorted(counts)


def test_partition_count_does_not_matter(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").limit(40)
    rows = [sorted(chunk.semantic_chunks(docs.repartition(p)).collect()) for p in (1, 4, 16)]
    assert rows[0] == rows[1] == rows[2]


def test_bleu_and_character_accuracy(spark):
    pairs = spark.createDataFrame([(1, "a b c d e", "a b c d e"), (2, "a b c d e", ""), (3, "a b c d e f g h", "a b c d"), (4, "a b c d", "d c b a")], "id int, ref string, hyp string")
    got = {r.id: r.bleu for r in measures.bleu(pairs).collect()}
    assert got[1] == 1.0 and got[2] == 0.0 and got[4] == 0.0
    assert got[3] == pytest.approx(math.exp(1 - 8 / 4), abs=1e-6)
    car = {r.id: r.car for r in measures.car_precision(pairs).collect()}
    assert car[1] == 1.0 and car[2] == 0.0 and car[4] == 1.0
    edit = {r.id: r.c for r in pairs.select("id", measures.car_edit(F.col("ref"), F.col("hyp")).alias("c")).collect()}
    assert edit[1] == 1.0 and edit[2] == 0.0


def test_ranking_measures(spark):
    ranked = spark.createDataFrame([(q, r, r if r != best else 100) for q, best in ((1, 1), (2, 10), (3, 11), (4, 20), (5, 99)) for r in range(1, 21)], "query_id int, rank int, id int")
    queries = spark.createDataFrame([(q,) for q in range(1, 6)], "query_id int")
    qrels = queries.select("query_id", F.lit(100).alias("id"))
    ten, twenty = (measures.ranking_measures(queries, ranked, qrels, k).first() for k in (10, 20))
    assert ten.mrr == pytest.approx((1 + 0.1) / 5) and ten.hit_rate == 0.4 and ten.precision == pytest.approx(2 / 50)
    assert ten.mrr <= twenty.mrr <= twenty.hit_rate


def test_maxsim_of_one_token_is_cosine():
    a, b = np.array([[1.0, 2.0]]), np.array([[2.0, 1.0]])
    assert maxsim(a, b) == pytest.approx(0.8) and maxsim(a, np.zeros((0, 2))) == 0.0
    assert (unit(np.zeros((1, 2))) == 0).all()


def _batch(spark):
    rows = [(r, p, [float(r + 1), float(p)], [float(p), float(r + 1)]) for r in range(4) for p in range(3)]
    return spark.createDataFrame(rows, "rank int, pos int, query array<double>, document array<double>")


def test_gather_cap_and_local(spark):
    batch = _batch(spark)
    rows = lambda df: {r["rank"]: r["loss"] for r in df.collect()}
    assert rows(losses.contrastive(batch, cap=100)) == rows(losses.contrastive(batch))
    assert rows(losses.contrastive(batch, cap=3)) == pytest.approx(rows(losses.contrastive(batch, gather=False)))
    assert losses.candidates(batch, cap=5).groupBy("rank").count().select("count").distinct().collect() == [(5,)]
    one = batch.where("rank = 0")
    assert rows(losses.contrastive(one)) == pytest.approx(rows(losses.contrastive(one, gather=False)))
    for r in losses.hybrid(batch, 1).collect():
        assert r["loss"] == pytest.approx((r["contrastive"] + r["late"]) / 2)


@pytest.mark.parametrize("kind", ["lora", "ia3"])
@pytest.mark.parametrize("loss", ["hybrid", "cl", "li"])
def test_gradient_by_finite_differences(kind, loss):
    rng = np.random.default_rng(0)
    adapter = encode.Adapter.start(kind, 6, 2)
    if kind == "lora":
        adapter.weights["B"] = rng.standard_normal((2, 6)) * 0.3
    queries, docs = [rng.standard_normal((n, 6)) for n in (2, 3)], [rng.standard_normal((n, 6)) for n in (4, 1)]
    others = unit(rng.standard_normal((2, 6)))
    value = lambda: (lambda c, s, _: (c + s) / 2 if loss == "hybrid" else c + s)(*train.loss_and_grad(adapter, queries, docs, others, loss, 0.5))
    grads = train.loss_and_grad(adapter, queries, docs, others, loss, 0.5)[2]
    for name, weights in adapter.weights.items():
        for at in [tuple(rng.integers(0, s) for s in weights.shape) for _ in range(5)]:
            old = weights[at]
            weights[at] = old + 1e-6
            up = value()
            weights[at] = old - 1e-6
            down = value()
            weights[at] = old
            assert grads[name][at] == pytest.approx((up - down) / 2e-6, abs=1e-5)


def test_training_falls_repeats_and_gathers_alike(spark):
    words = [f"w{i}" for i in range(60)]
    rows = [(f"{i}", f"{words[i]} {words[(i * 7) % 60]}", f"{words[i]} {words[(i * 7) % 60]} {words[(i * 3) % 60]} x y") for i in range(48)]
    pairs = spark.createDataFrame(rows, "pair_id string, question string, text string")
    cfg = dict(workers=2, batch=6, steps=4, cap=12, rate=0.1)
    first, log = train.fit(pairs, train.TrainConfig(**cfg))
    again, _ = train.fit(pairs, train.TrainConfig(**cfg))
    assert all((first.weights[k] == again.weights[k]).all() for k in first.weights)
    assert all(r["pairs"] == 12 for r in log)
    one, _ = train.fit(pairs, train.TrainConfig(**{**cfg, "steps": 1}))
    barrier, _ = train.fit(pairs, train.TrainConfig(**{**cfg, "steps": 1}, gather_mode="barrier"))
    sharded, _ = train.fit(pairs, train.TrainConfig(**{**cfg, "steps": 1}, shard_params=True))
    for other in (barrier, sharded):
        assert all(np.allclose(one.weights[k], other.weights[k], atol=1e-6) for k in one.weights)
    with pytest.raises(ValueError):
        train.others_of(0, 5, {}, 4)


def test_registry_holds_one_object():
    events = []

    class Model:
        def __init__(self, n):
            events.append(f"load {n}")
            self.n = n

        def close(self):
            events.append(f"close {self.n}")

    r = Registry()
    a = r.get(Model, 1)
    assert r.get(Model, 1) is a and r.get(Model, 2).n == 2
    assert events == ["load 1", "close 1", "load 2"] and (r.loads, r.hits) == (2, 1)


def test_warm_workers_load_less_than_cold_ones(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("text").repartition(12)
    spec = encode.EncoderSpec("small", True)
    cold = encode.registry_trace(docs, spec, warm=False).collect()
    before = {r.process: r.loads for r in cold}
    warm = encode.registry_trace(docs, spec).collect()
    loads = {r.process: max(x.loads for x in warm if x.process == r.process) for r in warm}
    # a worker that is used again loads at most once more over all its warm tasks, and every cold task loads
    assert len(cold) == len(warm) == 12
    assert sum(n - before.get(p, 0) for p, n in loads.items()) <= len(loads)
    assert len({(r.process, r.loads) for r in cold}) == 12


def test_int8_codes():
    codes, scale = index.quantise(np.array([[0.0, 0.0], [1.0, -2.0]]))
    assert scale[0] == 1.0 and codes.tolist() == [[0, 0], [64, -127]]


def test_all_probes_equal_exact(spark, sf):
    v = spark.read.parquet(f"{sf}/embeddings.parquet").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vector"))
    q = v.where("id % 100 = 0").select(F.col("id").alias("query_id"), "vector")
    seeds = v.where("id < 5").select(F.col("id").alias("cell"), F.col("vector").alias("seed"))
    exact = sorted(index.knn_gemm(q, v, 5).collect())
    assert sorted(index.knn_ivf(q, index.build_ivf(v, seeds), seeds, 5, 5).collect()) == exact
    assert sorted(index.knn_int8(q, index.codes_of(v), v, 5).collect()) == exact
    assert sorted(index.knn_gemm(q, v, 5, query_bytes=0).collect()) == exact  # blocks against blocks
    assert index.knn_gemm(q.limit(0), v, 5).count() == 0
    assert [index.plan_knn(q_, 10**9, 10) for q_ in (1, 50, 10**6)] == ["exact", "ivf+rescore", "ivf"]


def test_store_and_sources(spark, tmp_path, sf):
    from litspark.sources import readers, store

    v = spark.read.parquet(f"{sf}/embeddings.parquet").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vector")).limit(60)
    seeds = v.limit(4).select(F.col("id").alias("cell"), F.col("vector").alias("seed"))
    store.write_index(str(tmp_path / "ix"), v, v.select("id", F.lit("text").alias("text")), seeds, "v1")
    vectors, passages, _ = store.read_index(spark, str(tmp_path / "ix"), "v1")
    assert vectors.count() == 60 and store.fetch_passages(vectors.select("id").limit(3), passages).count() == 3
    with pytest.raises(ValueError):
        store.read_index(spark, str(tmp_path / "ix"), "v2")
    for kind in ("json", "csv", "orc", "parquet"):
        df = spark.createDataFrame([(1, 'a "b"\nc'), (2, "é")], "a int, b string")
        assert sorted(readers.round_trip(df, str(tmp_path / kind), kind).collect()) == sorted(df.collect())
    (tmp_path / "pages").mkdir()
    (tmp_path / "pages/x.html").write_text(PAGE)
    readers.register(spark)
    kinds = {r.kind for r in spark.read.format("html_regions").option("path", str(tmp_path / "pages")).load().collect()}
    assert "paragraph" in kinds
    assert parse.two_stage(readers.binary_pages(spark, str(tmp_path / "pages"))).count() == 1


def test_sql_functions(spark):
    from litspark.functions import sqlapi

    sqlapi.register_all(spark)
    row = spark.sql("SELECT rag_cosine(array(1D, 2D), array(2D, 1D)) AS c, rag_car('abc', 'abd') AS r, size(rag_embed('a b')) AS n").first()
    assert row.c == pytest.approx(0.8) and row.r == pytest.approx(2 / 3) and row.n == 64
    assert spark.sql("SELECT * FROM rag_chunks('A b. A b. C d.', 0.9D)").count() == 2
    assert spark.sql("SELECT count(*) AS n FROM (SELECT '<p>a</p><p>b</p>' AS h) t, LATERAL rag_regions(t.h)").first().n == 2


def test_exhausted_entities_are_dropped(spark):
    lines = spark.createDataFrame([(1, s, "A") for s in range(5)] + [(2, s, "R") for s in range(2)], "l_partkey long, l_suppkey long, l_returnflag string")
    part = spark.createDataFrame([(1, "x"), (2, "y")], "p_partkey long, p_name string")
    assert [r.item_id for r in qa.interaction_qa(lines, part).collect()] == [2]


def test_asof_and_range_joins(spark):
    left = spark.createDataFrame([(1, 10, 5), (2, 10, 1), (3, 11, 9)], "id long, k int, t int")
    right = spark.createDataFrame([(7, 10, 2), (8, 10, 5), (9, 10, 5)], "rid long, k int, t int")
    assert sorted(relational.asof_join(left, right, "k", "t", ["rid"], "rid").select("id", "asof_rid").collect()) == [(1, 9), (2, None), (3, None)]
    spans = spark.createDataFrame([(1, 0, 10), (2, 5, 25)], "s int, low int, high int")
    points = spark.createDataFrame([(0,), (5,), (10,), (24,), (25,)], "p int")
    assert sorted((r.p, r.s) for r in relational.range_join(points, spans, "p", "low", "high", 7).collect()) == [(0, 1), (5, 1), (5, 2), (10, 2), (24, 2)]


def test_lateral_does_not_lean_on_the_order_of_a_shuffle(spark, sf):
    """A window without an order takes the rows as the shuffle brings them: right on one machine, not on several."""
    plan = q_ops.QUERIES["op_lateral"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "o_totalprice" in plan and "windowspecdefinition" not in plan


def test_broadcast_join_counts_its_side(spark, sf, monkeypatch):
    plan = lambda: q_ops.QUERIES["op_join_broadcast"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "strategy=broadcast" in plan()
    monkeypatch.setattr(index, "BROADCAST_ROWS", 100)
    assert "strategy=broadcast" not in plan()


def _no_pairs(df):
    """No join of rows with rows of the other side in the plan."""
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan, plan
    return df


@pytest.mark.parametrize("query_bytes", [2**26, 0])
def test_searches_meet_in_blocks(spark, monkeypatch, query_bytes):
    monkeypatch.setattr(index, "SCORES", 64)
    rng = np.random.default_rng(7)
    v = rng.normal(size=(90, 8)).round(1)
    v[60:] = v[:30]  # copies: ties go to the smaller id
    rows = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "id long, vector array<float>").repartition(5)
    asked = rows.where("id % 9 = 0").select(F.col("id").alias("query_id"), "vector")
    seeds = rows.where("id < 5").select(F.col("id").alias("cell"), F.col("vector").alias("seed"))
    w = np.float32(v).astype(float)
    u = unit(w)
    cells = (u @ u[:5].T).round(9).argmax(axis=1)
    near = np.argsort(-(u @ u[:5].T).round(9), axis=1, kind="stable")[:, :2]
    signs = (w @ index.normals(8, 8).T > 0).reshape(90, 4, 2)
    late = np.array([[maxsim(a.reshape(-1, 4), b.reshape(-1, 4)) for b in w] for a in w])
    scores = {"nested": u @ u.T, "euclidean": -np.sqrt(((w[:, None] - w[None]) ** 2).sum(-1)), "late": late, "ivf": np.where((near[:, :, None] == cells[None, None]).any(1), u @ u.T, -np.inf), "lsh": np.where((signs[:, None] == signs[None]).all(-1).any(-1), u @ u.T, -np.inf)}
    monkeypatch.setattr(index, "search", lambda *args, f=index.search: f(*(*args, None)[:5], query_bytes))
    found = {
        "nested": index.knn_nested(asked, rows, 7), "euclidean": index.knn_nested(asked, rows, 7, "euclidean"), "late": index.maxsim_full(asked, rows, 7, 4),
        "ivf": index.knn_ivf(asked, index.build_ivf(rows, seeds), seeds, 7, 2), "lsh": index.knn_lsh(asked, rows, 7, 8, bits=8, bands=4),
    }
    for name, s in scores.items():
        want = {(q, i) for q in range(0, 90, 9) for i in sorted(np.flatnonzero(s[q] > -np.inf), key=lambda i: (-round(s[q, i], 6), i))[:7]}
        assert {(r.query_id, r.id) for r in (_no_pairs(found[name]) if query_bytes else found[name]).collect()} == want, name


@pytest.mark.parametrize("held", [2**26, 0])
def test_losses_meet_in_blocks(spark, monkeypatch, held):
    monkeypatch.setattr(losses, "ASKED", 3)
    monkeypatch.setattr(losses, "ANSWERED", 4)
    monkeypatch.setattr(losses, "QUERY_BYTES", held)
    rng = np.random.default_rng(3)
    q, d = rng.normal(size=(2, 30, 8))
    rank = np.arange(30) % 4 % 3  # ranks of different sizes
    batch = spark.createDataFrame([(int(r), i, q[i].tolist(), d[i].tolist()) for i, r in enumerate(rank)], "rank int, pos long, query array<double>, document array<double>").repartition(3)
    order = lambda r: sorted(range(30), key=lambda i: (rank[i] != r, rank[i], i))
    late = np.array([[maxsim(a.reshape(-1, 4), b.reshape(-1, 4)) / 2 for b in d] for a in q])

    def mean(s, many):
        out = {}
        for r in range(3):
            own = np.flatnonzero(rank == r)
            seen = order(r)[: many(len(own))]
            out[r] = np.mean([np.log(np.exp(s[i, seen] / losses.TAU).sum()) - s[i, i] / losses.TAU for i in own])
        return pytest.approx(out)

    rows = lambda df: {r["rank"]: r["loss"] for r in _no_pairs(df).collect()} if held else {r["rank"]: r["loss"] for r in df.collect()}
    pooled = unit(q) @ unit(d).T
    assert rows(losses.contrastive(batch, gather=False)) == mean(pooled, lambda n: n)
    assert rows(losses.contrastive(batch)) == mean(pooled, lambda n: 30)
    assert rows(losses.contrastive(batch, cap=10)) == mean(pooled, lambda n: max(n, 10))
    assert rows(losses.contrastive(batch, cap=3)) == mean(pooled, lambda n: n)
    assert rows(losses.late_interaction(batch, 4)) == mean(late, lambda n: n)


def test_a_stream_reads_a_table_of_several_files(spark, sf, tmp_path):
    pages = q_ops.load(spark, sf, "pages")
    pages.repartition(3).write.parquet(str(tmp_path / "pages.parquet"))
    chunks = lambda folder: sorted(ingest.drained(ingest.indexed_chunks(ingest.stream(spark, folder, "pages"))).collect())
    assert chunks(str(tmp_path)) == chunks(sf) == sorted(ingest.indexed_chunks(pages).collect()) != []


def test_hours_grow_with_the_samples(spark):
    samples = lambda n: spark.createDataFrame([("page", n), ("document", n), ("question", n)], "kind string, samples long")
    once, thrice = ({(r.stage, r.machine): r for r in costs.normalised(spark, samples(n)).collect()} for n in (16_400_000, 49_200_000))
    assert len(once) == len(costs.PUBLISHED) and once["train quantised", "system A"].epoch_hours == pytest.approx(1.303, abs=1e-3)
    assert all(thrice[k].epoch_hours == pytest.approx(3 * r.epoch_hours, abs=1e-3) and thrice[k].per_worker == r.per_worker for k, r in once.items())


def test_recursion_adds_up_the_orders_of_a_table(spark, sf):
    rows = q_ops.QUERIES["op_recursive_cte"](spark, sf).orderBy("y").collect()
    assert len(rows) > 2 and [r.so_far for r in rows] == list(np.cumsum([r.n for r in rows])) and rows[-1].so_far == q_ops.load(spark, sf, "orders").count()


def test_bleu_spreads_no_words(spark):
    pairs = spark.createDataFrame([("x", 1, "a b c d e", "a b c d e"), ("y", 1, "a b c d", None)], "parser string, id int, ref string, hyp string")
    found = measures.bleu(pairs, level="corpus", by="parser")
    assert "Generate" not in found._jdf.queryExecution().optimizedPlan().toString()
    assert {r.parser: r.bleu for r in found.collect()} == {"x": 1.0, "y": 0.0}


def test_late_rows_and_custom_state(spark, tmp_path):
    from litspark.streaming import ingest

    rows = [(i, f"2024-01-0{1 + i // 4} 0{i % 4}:00:00", i % 2, "a", 1.0, "{}") for i in range(12)]
    batch = spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    batch.coalesce(1).write.parquet(str(tmp_path / "raw"))
    next((tmp_path / "raw").glob("part-*.parquet")).rename(tmp_path / "events.parquet")
    live = ingest.stream(spark, str(tmp_path), "events")
    assert sorted(ingest.drained(ingest.windowed(live, "tumbling"), "complete").collect()) == sorted(ingest.windowed(batch, "tumbling").collect())
    # in append mode the last day never closes
    assert ingest.drained(ingest.windowed(ingest.stream(spark, str(tmp_path), "events"), "tumbling")).count() == 2
    seen = ingest.drained(ingest.running_users(ingest.stream(spark, str(tmp_path), "events")), "update").collect()
    assert sorted((r.user_id, r.events) for r in seen) == [(0, 6), (1, 6)]


def test_cost_shapes(spark):
    docs = spark.createDataFrame([(" ".join(["a"] * n),) for n in (8, 32, 128, 512, 512, 0)] + [(None,)], "text string")
    rows = costs.flop_model(docs).orderBy("tokens").collect()
    assert [(r.tokens, r.texts) for r in rows] == [(8, 3), (32, 1), (128, 1), (512, 2)]
    assert [r.ratio for r in rows] == sorted(r.ratio for r in rows) and rows[-1].ratio == 8 * 512
    assert costs.epoch_hours(16.4e6, 3496.4) == pytest.approx(1.303, abs=1e-3)
    assert costs.pair_ops(8, 100, "maxsim") == 800 and costs.pair_ops(8, 100, "cosine") == 1


def test_plans(spark, sf):
    """Chunking has no exchange; a filtered scan reads few columns and pushes the filter."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    said = chunk.semantic_chunks(docs.where("lang = 'en'"))._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in said and "PushedFilters" in said and "EqualTo(lang,en)" in said
    assert "source" not in said.split("ReadSchema")[1].split("\n")[0]


def test_index_recall(spark):
    """Recall against brute force of every approximate index at its registered parameters."""
    from litspark.plans import q_index, q_more

    sf = "/root/testdata/sf0.1"
    rows = {r.method: r.found / r.true_neighbours for r in q_index._recall(spark, sf).collect()}
    vectors = q_index._vectors(spark, sf)
    truth = index.knn_gemm(q_index._queries(vectors), vectors, q_index.K)
    r = index.recall(q_more.kmeans_ivf(spark, sf), truth).first()
    rows["kmeans"] = r.found / r.true_neighbours
    print(rows)
    assert set(rows) == {"int8", "ivf", "lsh", "kmeans"} and min(rows.values()) >= 0.9


def test_codes_are_scanned_without_vectors(spark, tmp_path, sf):
    v = spark.read.parquet(f"{sf}/embeddings.parquet").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vector"))
    index.codes_of(v).write.parquet(str(tmp_path / "codes"))
    codes = spark.read.parquet(str(tmp_path / "codes"))
    assert codes.count() == v.count() and all(len(r.code) == 64 for r in codes.limit(5).collect())
    q = v.where("id % 50 = 0").select(F.col("id").alias("query_id"), "vector")
    assert sorted(index.knn_int8(q, codes, v, 5).collect()) == sorted(index.knn_gemm(q, v, 5).collect())


def test_graph_edges_leave_crowded_sources(spark):
    from litspark.operators import clusters

    rows = [(i, [1.0, 0.001 * i], "a") for i in range(40)] + [(100 + i, [0.0, 1.0 + i], "b") for i in range(4)] + [(200, [1.0, 1.0], None)]
    vectors = spark.createDataFrame(rows, "id long, vector array<float>, source string")
    asked = vectors.where("id in (0, 100)").select(F.col("id").alias("query_id"), "vector", "source")
    got = {}
    for r in clusters.concept_graph(vectors, asked, 3).collect():
        got.setdefault(r.query_id, set()).add(r.id)
    assert got[0] == {200, 100, 101} and 200 in got[100] and len(got[100]) == 3


def test_late_interaction_on_text_tokens(spark):
    from litspark.operators import late

    texts = ["alpha beta gamma", "beta gamma delta epsilon", "", "zeta", "alpha beta gamma delta " * 3]
    passages = spark.createDataFrame(list(enumerate(texts)), "id long, text string").repartition(2)
    asked = spark.createDataFrame([(7, "beta gamma"), (8, "zeta alpha"), (9, "")], "query_id long, question string")
    for model in (late.Hashed(), late.Encoded()):
        rows = model.reader()
        q, p = late.token_index(asked, "question", "query_id", model), late.token_index(passages, "text", "id", model)
        want = {(a, i): maxsim(rows(x), rows(t)) for a, x in ((7, "beta gamma"), (8, "zeta alpha")) for i, t in enumerate(texts)}
        got = {(r.query_id, r.id): r.score for r in late.late_full(q, p, 5).collect()}
        assert got == pytest.approx(want, abs=1e-5)
        two = late.retrieve_late_interaction(q, p, spark.createDataFrame([(7, 0), (7, 3), (7, 3), (9, 0)], "query_id long, id long"), 5)
        assert {(r.query_id, r.id): r.score for r in two.collect()} == pytest.approx({(7, 0): want[7, 0], (7, 3): want[7, 3], (9, 0): 0.0}, abs=1e-5)


def _small_pairs(spark):
    words = [f"w{i}" for i in range(60)]
    rows = [(f"{i}", f"{words[i]} {words[(i * 7) % 60]}", f"{words[i]} {words[(i * 7) % 60]} {words[(i * 3) % 60]} x y") for i in range(48)]
    return spark.createDataFrame(rows, "pair_id string, question string, text string")


def test_training_in_one_stage_equals_step_by_step(spark):
    data = _small_pairs(spark)
    for more in ({}, {"gather": False}, {"loss": "cl", "adapter": "ia3"}):
        cfg = train.TrainConfig(workers=2, batch=6, steps=3, cap=12, rate=0.1, **more)
        one, log = train.fit(data, cfg)
        two, again = train.fit_in_stage(data, cfg)
        assert all(np.allclose(one.weights[k], two.weights[k], atol=1e-9) for k in one.weights)
        assert [r["loss"] for r in log] == pytest.approx([r["loss"] for r in again]) and all(r["pairs"] == 12 for r in again)
    with pytest.raises(ValueError):
        train.fit_in_stage(data, train.TrainConfig(workers=1000))


def test_sharded_parameters_are_shares(spark):
    from litspark.plans import costs, q_ops

    assert [train.shard_columns(10, p, 3) for p in range(3)] == [slice(0, 3), slice(3, 6), slice(6, 10)]
    cfg = train.TrainConfig(workers=2, batch=6, steps=3, cap=12, rate=0.1)
    whole, log = train.fit_in_stage(_small_pairs(spark), cfg)
    shared, slow = train.fit_in_stage(_small_pairs(spark), train.TrainConfig(workers=2, batch=6, steps=3, cap=12, rate=0.1, shard_params=True))
    assert all((whole.weights[k] == shared.weights[k]).all() for k in whole.weights)
    a, b = (costs.training_rates(x, 2, 64, 8, 6) for x in (log, slow))
    # each step sends at least the whole table once; the replicas send vectors and gradients only
    assert b["sent_mb"] > 3 * 4 * 2**14 * 64 / 1e6 > a["sent_mb"] and a["flops"] == b["flops"] > 0 and a["samples"] == 36


@pytest.mark.parametrize("name, steps", [("retrieval_table", 2), ("answering_table", 2), ("training_performance", 2), ("training_scaling", 2)])
def test_experiment_tables_are_whole(spark, sf, name, steps):
    from litspark.plans import q_tables

    rows = q_tables.QUERIES[name](spark, sf, steps).collect()
    if name == "retrieval_table":
        assert len(rows) == 9 and all(0 <= r[m] <= 1 for r in rows for m in ("p10", "mrr10", "mrr20", "top20")) and all(r.mrr20 <= r.top20 for r in rows)
    elif name == "answering_table":
        assert len(rows) == 35 - 7 * (len({r.benchmark for r in rows}) < 5) and {r.benchmark for r in rows} >= {"cloze", "yesno", "fulltext", "function"}
    elif name == "training_performance":
        assert {r.run for r in rows} == set(q_tables.RUNS) and all(r.samples == 2 * 96 and r.tflops_per_worker > 0 for r in rows)
        by = {r.run: r for r in rows}
        assert by["large, low-rank, sharded and offloaded"].samples_per_s < by["large quantised, low-rank"].samples_per_s
    else:
        assert [(r.workers) for r in rows] == [1, 2, 4] * 3 and all(r.efficiency > 0 for r in rows)
    spark.catalog.clearCache()


def test_rarest_tokens_both_ways(spark, sf, monkeypatch):
    from litspark.operators import pairs

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    made = chunk.semantic_chunks(docs).persist()
    near = sorted(pairs.synth_questions(made, docs).collect())
    monkeypatch.setattr(pairs, "VOCABULARY", 10)
    monkeypatch.setattr(pairs, "COMMON", 20)
    assert sorted(pairs.synth_questions(made, docs).collect()) == near and len(near) > 100


def test_edit_accuracy_equals_brute_force(spark):
    from litspark.functions import measures

    def distance(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            last, row[0] = row[0], i
            for j, y in enumerate(b, 1):
                last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
        return row[-1]

    rng = np.random.default_rng(3)
    rows = [("", ""), ("", "x"), ("abc", ""), ("é" * 90, "è" * 80), ("ab" * 500, "ba" * 400)]
    rows += [("".join(rng.choice(list("abé "), n)), "".join(rng.choice(list("abé "), m))) for n, m in rng.integers(0, 200, (20, 2))]
    got = spark.createDataFrame(rows, "ref string, hyp string").select("ref", "hyp", measures.car_edit(F.col("ref"), F.col("hyp")).alias("car")).collect()
    for r in got:
        want = float(r.hyp == "") if not r.ref else max(0.0, 1 - distance(r.ref, r.hyp) / len(r.ref))
        assert r.car == pytest.approx(want)


def test_edit_distance_of_long_texts_costs_their_length(spark):
    import time

    text = "".join(np.random.default_rng(5).choice(list("abcdé "), 120_000))
    more = text[:700] + "menu " * 9_000 + text[700:]
    began = time.perf_counter()
    got = spark.createDataFrame([(text, more), (more, text), (text, text)], "ref string, hyp string").select(measures.edit_distance(F.col("ref"), F.col("hyp")).alias("d")).collect()
    assert [r.d for r in got] == [45_000, 45_000, 0]
    assert time.perf_counter() - began < 15  # a table of 120,000 by 165,000 takes longer
    # neither text lies in the other
    assert measures.distance("xx" + text[:3000] + "yy", "z" + text[:1500] + "-" + text[1500:3000]) == 5


def test_near_pairs_of_classes_and_common_shingles(spark, monkeypatch):
    monkeypatch.setattr(relational, "LOCAL", 2)
    rng = np.random.default_rng(11)
    line = "this very line stands in all of these texts"
    texts = [" ".join(rng.choice(list("abcdefghij"), 40)) + " " + line for _ in range(12)]
    texts += [texts[0], texts[0], texts[1] + " tail", texts[1] + " tail", texts[2][:-20], "a b", "", None, line]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in ((t or "").split() for t in texts)]
    want = {(a, b, len(x & y), len(x | y)) for a, x in enumerate(sets) for b, y in enumerate(sets) if a < b and x and y and 100 * len(x & y) >= 75 * len(x | y)}
    found = relational.near_pairs(rows)
    assert sorted(tuple(r) for r in found.collect()) == sorted(want) and len(want) > 5
    # whole sets are not shuffled by shingle: only the heads are
    heads = relational._heads(relational._shingles(rows, 5), 75).collect()
    assert all(len(r.head) == r.n - math.ceil(r.n * 75 / 100) + 1 for r in heads)


def test_equal_questions_are_asked_once(spark, monkeypatch):
    rng = np.random.default_rng(4)
    base = rng.integers(0, 3, (6, 8)).astype(float)
    asked = spark.createDataFrame([(i, base[i % 6].tolist()) for i in range(40)], "query_id long, vector array<float>").repartition(3)
    vectors = spark.createDataFrame([(i, rng.integers(0, 3, 8).astype(float).tolist()) for i in range(50)], "id long, vector array<float>")
    stand, members = index.alike(asked)
    assert sorted(r.query_id for r in stand.collect()) == list(range(6))
    assert sorted(tuple(r) for r in members.collect()) == [(i, i % 6) for i in range(40)]
    passages = vectors.select(F.col("id").alias("passage_id"), F.concat(F.lit("p"), "id").alias("text"))
    items = asked.select(F.col("query_id").alias("item_id"))
    want = sorted(qa.augment(items, index.knn_gemm(asked, vectors, 3), passages).collect())
    assert sorted(qa.found_contexts(items, asked, vectors, passages, 3).collect()) == want
    # larger query sets go in slices, each a pass of its own
    monkeypatch.setattr(index, "BLOCK_ROWS", 4)
    sliced = index.knn_gemm(asked, vectors, 3, query_bytes=4 * 8 * 8)
    assert "CartesianProduct" not in (plan := sliced._jdf.queryExecution().toString()) and "NestedLoop" not in plan
    assert sorted(sliced.collect()) == sorted(index.knn_gemm(asked, vectors, 3).collect())


def test_chunk_guard_and_centroid(spark):
    said = ["a b c", "a b d", "a b e f g", "x y", "x"]
    assert chunk.cut(said) == [(0, 2, 11), (3, 4, 3)]
    assert chunk.cut(said, max_tokens=6) == [(0, 1, 6), (2, 2, 5), (3, 4, 3)]
    assert chunk.cut(said, max_tokens=2) == [(0, 0, 3), (1, 1, 3), (2, 2, 5), (3, 3, 2), (4, 4, 1)]
    from fractions import Fraction

    drift = ["a a a", "a b", "b b c", "c"]
    assert len(chunk.cut(drift, Fraction(1, 4), centroid=True)) >= len(chunk.cut(drift, Fraction(1, 4)))
    assert chunk.cut([], centroid=True) == [] and chunk.cut(["!"], centroid=True) == [(0, 0, 0)]


def test_metadata_of_authors_citations_and_references(spark):
    page = '<html lang="en"><head><meta name="author" content="A. One"></head><body><p class="byline">B.  <b>Two</b></p><p>As said [1], and [2-4] and [1] in <cite>Some Book</cite>.</p><ol class="references"><li>First, 1999.</li><li>Second</li></ol></body></html>'
    meta = parse.metadata(spark.createDataFrame([(1, "http://x/en/1", page), (2, None, None)], "page_id long, url string, html string")).collect()
    got = {r.page_id: r.meta for r in meta}
    assert got[1]["authors"] == "A. One; B. Two" and got[1]["citations"] == "Some Book; [1]; [2-4]" and got[1]["references"] == "First, 1999.; Second"
    assert got[2]["authors"] == got[2]["citations"] == got[2]["references"] == ""


def test_stage_farm(spark, tmp_path, sf):
    from litspark.sources import store

    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    made, report = store.run_stage("chunk", docs, chunk.semantic_chunks, rows_per_task=30, path=str(tmp_path / "out"))
    assert report["rows"] == 200 and report["tasks"] == 7 and report["seconds"] > 0
    assert sorted(made.collect()) == sorted(chunk.semantic_chunks(docs).collect())


ODD = ["One two three. Two three four! Five\n\nsix seven. Six seven eight", "", None, " \n ", "...", "Ünïcode große Straße. Große Straße!\nΣΑΣ ΣΑΣ. Ως ΣΑΣ", "a b c. c d e. " * 40, "日本 語. 日本\nx_y x_y. x y"]


def test_chunks_by_arrays_equal_the_sentence_by_sentence_cut(spark, monkeypatch):
    monkeypatch.setattr(chunk, "HELD_SENTENCES", 7)
    for threshold in (Fraction(1, 10), Fraction(1, 2), Fraction(1001, 2000), Fraction(0)):
        for names, said in chunk._held(list(range(len(ODD))), ODD):
            starts, firsts, tokens, _ = chunk._cuts(said, threshold, 64)
            ends = np.append(starts[1:], len(tokens))
            got = [(int(a - firsts[a]), int(b - firsts[a] - 1), int(tokens[a:b].sum())) for a, b in zip(starts, ends)]
            assert got == [c for own in said for c in chunk.cut(own, threshold)]
    docs = spark.createDataFrame(list(enumerate(ODD)), "doc_id long, text string")
    made = chunk.semantic_chunks(docs).persist()
    whole = [(i, no, ". ".join(own[a : b + 1])) for i, own in enumerate(map(split_sentences, ODD)) for no, (a, b, _) in enumerate(chunk.cut(own))]
    assert sorted(tuple(r) for r in made.select("doc_id", "chunk_no", "text").collect()) == whole
    want = encode.hashed_vectors(made.withColumn("id", F.col("doc_id") * 1000 + F.col("chunk_no")), "text", "id").collect()
    got = chunk.chunk_vectors(docs).select((F.col("doc_id") * 1000 + F.col("chunk_no")).alias("id"), "vector").collect()
    assert sorted(got) == sorted(want)


def test_own_ranks_are_those_of_the_search(spark):
    rng = np.random.default_rng(3)
    v = rng.integers(0, 3, (600, 8)).astype(float)  # many ties
    v[5] = 0
    vectors = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "id long, vector array<float>")
    asked = {i: np.maximum(v[i] - rng.integers(0, 2, 8), 0) for i in range(0, 600, 7)} | {5: v[5]}
    queries = spark.createDataFrame([(i, x.tolist(), v[i].tolist()) for i, x in asked.items()], "query_id long, vector array<float>, own array<float>")
    want = index.knn_gemm(queries.select("query_id", "vector"), vectors, 20).where("query_id = id").select("query_id", "rank", "id").collect()
    assert 5 < len(want) < len(asked)
    for size in (index.QUERY_BYTES, 100):  # one slice, several slices
        assert sorted(index.own_ranks(queries, index.rounds(vectors, "id"), 20, size).collect()) == sorted(want)
    assert sorted(r.id for p in index.rounds(vectors, "id") for r in p.collect()) == list(range(600))
    assert index.own_ranks(queries.where("query_id < 0"), [vectors], 20).count() == 0


@pytest.mark.parametrize("encoded", [False, True])
def test_texts_are_scored_as_by_their_token_indexes(spark, encoded):
    from litspark.operators import late

    model = late.Encoded() if encoded else late.Hashed()
    questions = spark.createDataFrame([(1, "one two three"), (2, ""), (3, "two two")], "query_id long, question string")
    passages = spark.createDataFrame([(10, "three two one. two"), (11, None), (12, "none of it"), (13, "two")], "id long, text string")
    pairs = questions.select("query_id").crossJoin(passages.select("id"))
    want = late.scored_pairs(pairs, late.token_index(questions, "question", "query_id", model), late.token_index(passages, "text", "id", model))
    got = late.scored_texts(pairs.union(pairs), questions, passages, model)
    assert sorted((r.query_id, r.id, round(r.score, 9)) for r in got.collect()) == sorted((r.query_id, r.id, round(r.score, 9)) for r in want.collect())


def test_held_out_measures_of_late_interaction_keep_no_token_rows(spark, sf):
    from pyspark.sql import functions as F

    from litspark.functions.measures import ranking_measures
    from litspark.operators import late
    from litspark.plans import q_tables

    sets = q_tables.Sets(spark, sf)
    chunks = chunk.semantic_chunks(sets.docs).withColumn("id", q_tables.chunk_number())
    q = q_tables._as_queries(q_tables._hashed(sets.asked, "question", "query_id"))
    near = index.knn_gemm(q, q_tables._hashed(chunks, "text", "id"), q_tables.HELD_FIRST)
    model = late.Hashed()
    held = late.retrieve_late_interaction(late.token_index(sets.asked, "question", "query_id", model), late.token_index(chunks, "text", "id", model), near, q_tables.HELD_TOP)
    want = ranking_measures(sets.asked, held, sets.truth, q_tables.HELD_TOP).select(F.col("queries").alias("heldout_queries"), F.col("mrr").alias("mrr20"), F.col("hit_rate").alias("top20"))
    assert sets.held_measures(q_tables._hashed, model).collect() == want.collect()


def test_banked_encoders_equal_each_by_itself(spark, sf):
    import numpy as np

    from litspark.operators import encode

    texts = ["", "One", "one two", "One two three.", None, "a b c d e f g, and again a b c", "two one"]
    scaled = encode.Adapter("ia3", {"s": np.linspace(0.5, 2, 64)})
    low = encode.Adapter("lora", {"A": np.random.default_rng(1).standard_normal((256, 8)), "B": np.random.default_rng(2).standard_normal((8, 256)) / 50})
    states = [(encode.EncoderSpec(), scaled, None), (encode.EncoderSpec("large", True), low, None), (encode.EncoderSpec(), None, {"one": 3.0, "a": 0.5})]
    for state, got in zip(states, encode.Bank(states).texts(texts)):
        one = encode.Encoder(*state)
        rows = [one.tokens(t or "") for t in texts]
        want = np.array([r.mean(axis=0) if len(r) else np.zeros(r.shape[1]) for r in rows])
        want /= np.maximum(np.linalg.norm(want, axis=1, keepdims=True), 1e-30)
        assert got.dtype == np.float32 and np.abs(got - want).max() < 1e-6 and not got[0].any()
        assert (got == one.pooled(texts).astype(np.float32)).all()
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(60)
    made = chunk.semantic_chunks(docs).selectExpr("doc_id * 100000 + chunk_no AS id", "text")
    want = {r.id: r.vector for r in encode.with_pooled(made, "text", "id", *states[1][:2]).collect()}
    assert {r.id: r.vector for r in encode.chunk_pooled(docs, states[1]).collect()} == want and len(want) > 60


def test_own_ranks_of_several_encoders(spark):
    import numpy as np

    from litspark.operators import index

    rng = np.random.default_rng(7)
    sides = [np.round(rng.standard_normal((300, d)) * 2) for d in (4, 9)]
    asked = [s[::10] + rng.standard_normal((30, s.shape[1])) for s in sides]
    blocks = spark.range(1).coalesce(1).mapInArrow(lambda _: iter([index.own_block(np.arange(0, 300, 10), list(zip(asked, [s[::10] for s in sides])))]), index.OWN)

    def read(batches):
        for batch in batches:
            at = batch.column("id").to_numpy()
            yield at, [s[at] for s in sides]

    parts = index.rounds(spark.range(300), "id")
    found = index.own_ranks_of(blocks, parts, read, [5, 40])
    for got, q, v, k in zip(found, asked, sides, (5, 40)):
        named = lambda key, rows, ids: spark.createDataFrame([(int(i), [float(np.float32(x)) for x in r]) for i, r in zip(ids, rows)], f"{key} long, vector array<float>")
        near = index.knn_gemm(named("query_id", q, range(0, 300, 10)), named("id", v, range(300)), k).where("query_id = id")
        assert sorted((r.query_id, r.rank) for r in got.collect()) == sorted((r.query_id, r.rank) for r in near.collect()) != []


def test_rough_scores_keep_the_same_best():
    import numpy as np

    from litspark.functions.vectors import unit
    from litspark.operators import index

    rng = np.random.default_rng(3)
    v = np.round(rng.standard_normal((5000, 6)) * 1.5)  # many equal vectors and equal scores
    q, ids = np.round(rng.standard_normal((20, 6)) * 1.5), rng.permutation(5000)
    exact, sifted, score = index._Kept(7), index._Kept(7), index._Cosine(q)
    for at in range(0, 5000, 1250):
        w = unit(v[at : at + 1250])
        exact.add(np.arange(20), score.u @ w.T, ids[at : at + 1250])
        score.sift(sifted, np.arange(20), w, w.astype(np.float32), ids[at : at + 1250])
    for name in range(20):
        # products of whole matrices may differ in the last bit, so scores are told apart by the sixth digit only
        assert (np.abs(exact.best[name][0] - sifted.best[name][0]) < 1.5e-6).all() and (exact.best[name][1] == sifted.best[name][1]).all()


def test_drawn_pairs_are_the_first_training_pairs(spark, sf):
    from pyspark.sql import functions as F

    from litspark.operators import pairs
    from litspark.plans import q_qa

    every = q_qa._training_pairs(spark, sf)
    docs = q_qa._docs(spark, sf)
    for size in (50, 1_000_000):
        want = every.orderBy(F.md5("pair_id"), "pair_id").limit(size).select("pair_id", "question", "text").collect()
        got = pairs.drawn_pairs(docs, size, pairs.document_frequency(docs)).select("pair_id", "question", "text").collect()
        assert sorted(got) == sorted(want) and len(want) >= 50


def test_late_loss_of_a_batch_equals_pair_by_pair():
    import numpy as np

    from litspark.functions.vectors import maxsim
    from litspark.operators import encode, train

    rng = np.random.default_rng(5)
    q, d = [rng.standard_normal((n, 8)) for n in (3, 0, 5)], [rng.standard_normal((n, 8)) for n in (4, 6, 0)]
    adapter = encode.Adapter("ia3", {"s": np.linspace(0.5, 1.5, 8)})
    scores = np.array([[maxsim(adapter.apply(a), adapter.apply(b)) / max(len(a), 1) / 0.1 for b in d] for a in q])
    want = -(np.diag(scores) - np.log(np.exp(scores).sum(axis=1))).mean()
    _, late, grads = train.loss_and_grad(adapter, q, d, None, "li", 0.1)
    moved = []
    for sign in (1, -1):
        other = encode.Adapter("ia3", {"s": adapter.weights["s"] + sign * 1e-6 * np.eye(8)[2]})
        moved.append(train.loss_and_grad(other, q, d, None, "li", 0.1)[1])
    assert abs(late - want) < 1e-9 and abs((moved[0] - moved[1]) / 2e-6 - grads["s"][2]) < 1e-4


#: Pages whose text lies outside of a first article: no article, neither article nor body, two articles, nothing at all.
WHOLE = {
    11: ("<html><head><title>Tab</title></head><body class='x'><h1>Roots</h1><script>var a = 1;</script><p>of a tree &amp; more of them</p></body></html>", "Roots of a tree & more of them"),
    12: ("<title>Tab</title><p>plain words that stand alone</p>", "plain words that stand alone"),
    13: ("<body><div><article><h1>First</h1><p>one two three</p></article></div><article><p>four five six</p></article></body>", "First one two three four five six"),
    14: ("", ""),
}


@pytest.fixture(scope="module")
def whole_pages(tmp_path_factory):
    """A folder of ``pages`` and ``documents``, and DuckDB over them."""
    import duckdb

    folder, con = tmp_path_factory.mktemp("pages"), duckdb.connect()
    con.sql("CREATE TABLE pages (page_id BIGINT, url VARCHAR, html VARCHAR)")
    con.sql("CREATE TABLE documents (doc_id BIGINT, text VARCHAR)")
    for i, (page, text) in WHOLE.items():
        con.execute("INSERT INTO pages VALUES (?, ?, ?)", [i, f"http://a.b/en/{i}", page])
        con.execute("INSERT INTO documents VALUES (?, ?)", [i, text])
    for name in ("pages", "documents"):
        con.sql(f"COPY {name} TO '{folder / name}.parquet' (FORMAT parquet)")
    return str(folder), con


def test_end_to_end_reads_pages_outside_of_a_first_article(spark, whole_pages):
    from litspark.plans import q_parse

    folder, con = whole_pages
    assert {i: parse.end_to_end_text(page) for i, (page, _) in WHOLE.items()} == {i: text for i, (_, text) in WHOLE.items()}
    same_rows(q_parse.QUERIES["parse_end_to_end"](spark, folder), con.sql(q_parse.ORACLES["parse_end_to_end"]))


def test_corpus_bleu_of_pages_outside_of_a_first_article(spark, whole_pages):
    from litspark.plans import q_parse

    folder, con = whole_pages
    got, want = {r.parser: r.bleu for r in q_parse.QUERIES["parser_bleu_corpus"](spark, folder).collect()}, dict(con.sql(q_parse.ORACLES["parser_bleu_corpus"]).fetchall())
    assert got["end_to_end"] == want["end_to_end"] == 1


def test_edit_accuracy_of_pages_outside_of_a_first_article(spark, whole_pages):
    from litspark.plans import q_parse

    found = {r.parser: (r.pages, r.car) for r in q_parse.QUERIES["parser_car_edit"](spark, whole_pages[0]).collect()}
    assert found["end_to_end"] == (4, 1)


@pytest.mark.parametrize("k", [3, 70])
def test_counted_search_is_the_search_of_the_vectors(spark, monkeypatch, k):
    from litspark.operators import counted

    monkeypatch.setattr(counted, "HELD", 100)
    rng = np.random.default_rng(3)
    words = [f"w{i}" for i in range(60)]
    said = lambda n: " ".join(rng.choice(words, n))
    passages = spark.createDataFrame([(i, said(int(rng.integers(0, 12)))) for i in range(340)] + [(900, None), (901, ""), (902, "w1 w1 w1")], "id long, text string").repartition(3)
    asked = spark.createDataFrame([(i, f"what is {said(2)}") for i in range(50)] + [(70, ""), (71, "w1 w1 w2"), (72, None), (73, "none of these")], "item_id long, question string")
    coded = counted.codes(asked, "question", "item_id", 16)
    vectors = encode.hashed_vectors(asked, "question", "item_id", 16).select(F.col("id").alias("query_id"), "vector")
    got = counted.knn_counts(coded.withColumnRenamed("id", "query_id"), passages, "text", "id", k, 16)
    want = sorted(index.knn_gemm(vectors, encode.hashed_vectors(passages, "text", "id", 16), k).collect())
    assert sorted(got.collect()) == want and len(want) == 54 * k
    monkeypatch.setattr(counted, "ASKED", 10)
    assert sorted(counted.knn_counts(coded.withColumnRenamed("id", "query_id"), passages, "text", "id", k, 16).collect()) == want
    monkeypatch.setattr(counted, "SLICES", 2)  # more than slices hold
    assert sorted(counted.knn_counts(coded.withColumnRenamed("id", "query_id"), passages, "text", "id", k, 16).collect()) == want


def test_hashed_contexts_are_the_found_contexts(spark):
    items = spark.createDataFrame([(i, f"part {i % 4} ring", "a | b") for i in range(12)], "item_id long, question string, options string")
    passages = spark.createDataFrame([(i, f"part {i % 6} ring of {'a' if i % 2 else 'b'}") for i in range(30)], "passage_id long, text string")
    queries = encode.hashed_vectors(items, "question", "item_id", 512).select(F.col("id").alias("query_id"), "vector")
    want = sorted(qa.found_contexts(items, queries, encode.hashed_vectors(passages, "text", "passage_id", 512), passages, 3).collect())
    got = qa.hashed_contexts(items, passages, 512, 3)
    assert sorted(got.select("item_id", "context").collect()) == want
    answered = items.withColumn("answer_idx", F.lit(0))
    assert sorted(qa.answers(answered, got).collect()) == sorted(qa.answers(answered, got.drop("words")).collect())


def test_early_distractors_are_those_of_all_draws(spark, monkeypatch):
    lines = spark.createDataFrame([(p, s, "ANR"[(p + s) % 3]) for p in range(40) for s in range(30) if (p * 7 + s * 3) % (2 + p % 9) == 0] + [(1, 99, "X")], "l_partkey long, l_suppkey long, l_returnflag string")
    part = spark.createDataFrame([(p, f"name {p}") for p in range(40)], "p_partkey long, p_name string")
    found = sorted(qa.interaction_qa(lines, part).collect())
    monkeypatch.setattr(qa, "FEW", 100)  # all at once
    assert found == sorted(qa.interaction_qa(lines, part).collect()) and 0 < len(found)
    assert not any("supplier 99" in r.options for r in found)
