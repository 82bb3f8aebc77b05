"""Queries on page parsing, its baselines and its measures, with their SQL."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from litspark.catalog import load
from litspark.functions import measures
from litspark.operators import parse


def _pages(spark, sf_dir):
    return load(spark, sf_dir, "pages")


def q_regions(spark, sf_dir):
    return parse.detect_layout(_pages(spark, sf_dir)).select("page_id", "region_no", "kind", "role", "text")


def q_census(spark, sf_dir):
    return parse.detect_layout(_pages(spark, sf_dir), ()).groupBy("kind", "role").agg(F.count("*").alias("regions"), F.count_distinct("page_id").alias("pages"))


def q_metadata(spark, sf_dir):
    return parse.metadata(_pages(spark, sf_dir)).select("page_id", F.explode("meta").alias("key", "value"))


def q_parsed_pages(spark, sf_dir):
    return parse.two_stage(_pages(spark, sf_dir)).select("page_id", "text")


def q_assembled(spark, sf_dir):
    return parse.assemble(parse.detect_layout(_pages(spark, sf_dir), parse.TEXT_KINDS)).select("page_id", "text")


def q_parsed_documents(spark, sf_dir):
    return parse.documents_of(parse.two_stage(_pages(spark, sf_dir)))


def _parser(name):
    return lambda spark, sf_dir: parse.PARSERS[name](_pages(spark, sf_dir)).select("page_id", "text")


def q_failures(spark, sf_dir):
    pages = _pages(spark, sf_dir)
    routes = pages.select(parse.route(F.col("html")).alias("route")).groupBy("route").agg(F.count("*").alias("pages"))
    return routes


def q_failure_rate(spark, sf_dir):
    return parse.parse_extract(_pages(spark, sf_dir)).agg(F.count("*").alias("files"), F.sum(F.col("failed").cast("long")).alias("failed"), F.round(F.avg(F.col("failed").cast("double")), 6).alias("rate"))


def q_split_pages(spark, sf_dir):
    return parse.split_pages(load(spark, sf_dir, "documents", "doc_id", "text"))


def _pairs(spark, sf_dir, name):
    truth = load(spark, sf_dir, "documents", "doc_id", "text").select("doc_id", measures.squeezed(F.col("text")).alias("ref"))
    parsed = parse.PARSERS[name](_pages(spark, sf_dir)).withColumn("doc_id", parse.doc_id(F.col("url")))
    return parsed.join(truth, "doc_id").select(F.col("page_id").alias("id"), "ref", F.col("text").alias("hyp"))


def q_bleu(spark, sf_dir):
    return measures.bleu(_pairs(spark, sf_dir, "extract")).withColumnRenamed("id", "page_id")


MEASURED = ("two_stage", "extract", "hybrid3", "end_to_end")


def _measured(spark, sf_dir):
    """(parser, id, ref, hyp) of every measured parser; the documents that a page shows are joined once for all of them."""
    parsed = reduce(lambda a, b: a.unionByName(b), [parse.PARSERS[n](_pages(spark, sf_dir)).withColumn("parser", F.lit(n)) for n in MEASURED])
    shown = _pages(spark, sf_dir).select(parse.doc_id(F.col("url")).alias("doc_id")).distinct()
    truth = load(spark, sf_dir, "documents", "doc_id", "text").join(shown, "doc_id", "left_semi").select("doc_id", measures.squeezed(F.col("text")).alias("ref"))
    return parsed.withColumn("doc_id", parse.doc_id(F.col("url"))).join(truth, "doc_id").select("parser", F.col("page_id").alias("id"), "ref", F.col("text").alias("hyp"))


def q_bleu_corpus(spark, sf_dir):
    return measures.bleu(_measured(spark, sf_dir), level="corpus", by="parser")


def q_car_precision(spark, sf_dir):
    rows = [measures.car_precision(_pairs(spark, sf_dir, n)).agg(F.round(F.avg("car"), 6).alias("car")).select(F.lit(n).alias("parser"), "car") for n in MEASURED]
    return reduce(lambda a, b: a.unionByName(b), rows)


def q_car_edit(spark, sf_dir):
    """Edit-distance character accuracy of every measured parser over all pages and whole texts."""
    value = measures.car_edit(F.col("ref"), F.coalesce("hyp", F.lit("")))
    found = _measured(spark, sf_dir).select("parser", value.alias("car")).groupBy("parser").agg(F.count("*").alias("pages"), F.avg("car").alias("car"))
    every = spark.createDataFrame([(n,) for n in MEASURED], "parser string")
    return every.join(found, "parser", "left").select("parser", F.coalesce("pages", F.lit(0)).alias("pages"), F.round("car", 6).alias("car"))


def q_sample(spark, sf_dir):
    return parse.stratified_sample(_pages(spark, sf_dir)).select("page_id", "stratum")


def q_assets(spark, sf_dir):
    found = parse.detect_layout(_pages(spark, sf_dir))
    return found.groupBy("page_id").agg(F.count(F.when(F.col("role") == "asset", 1)).alias("assets"), F.count("*").alias("regions"))


ENT = "replace(replace(replace(replace(replace(replace({0}, '&quot;', '\"'), '&copy;', '©'), '&middot;', '·'), '&lt;', '<'), '&gt;', '>'), '&amp;', '&')"
SQUEEZE = r"trim(regexp_replace({0}, '\s+', ' ', 'g'))"
_bare = r"regexp_replace({0}, '<[^>]*>', '', 'g')"
_clean = SQUEEZE.format(ENT.format(_bare.format("{0}")))


def clean(s: str) -> str:
    return SQUEEZE.format(ENT.format(_bare.format(s)))


REGIONS = rf"""
base AS (SELECT page_id, regexp_extract(html, '<nav>(.*)</nav>', 1, 's') AS nav, regexp_extract(html, '<div class="ad">(.*?)</div>', 1, 's') AS ad,
  regexp_extract(html, '<h1>(.*?)</h1>', 1, 's') AS h1, regexp_extract(html, '</h1>(.*)</article>', 1, 's') AS body, regexp_extract(html, '<footer>(.*)</footer>', 1, 's') AS foot FROM pages),
parts AS (
  SELECT page_id, 1 AS part, generate_subscripts(l, 1) AS n, unnest(l) AS t, 'header_nav' AS kind FROM (SELECT page_id, regexp_split_to_array(nav, '</li>') AS l FROM base)
  UNION ALL SELECT page_id, 2, 1, ad, 'advert' FROM base UNION ALL SELECT page_id, 3, 1, h1, 'title' FROM base
  UNION ALL SELECT page_id, 4, generate_subscripts(l, 1), unnest(l), 'paragraph' FROM (SELECT page_id, regexp_split_to_array(replace(body, '<br>', ' '), '</?p>') AS l FROM base)
  UNION ALL SELECT page_id, 5, 1, foot, 'footer' FROM base),
said AS (SELECT page_id, part, n, kind, {clean('t')} AS text FROM parts),
regions AS (SELECT page_id, (row_number() OVER (PARTITION BY page_id ORDER BY part, n) - 1)::INT AS region_no, kind,
  CASE kind WHEN 'title' THEN 'metadata' WHEN 'paragraph' THEN 'content' ELSE 'boilerplate' END AS role, text FROM said WHERE text <> '')"""
TRUTH = r"truth AS (SELECT page_id, url, d.doc_id, trim(regexp_replace(coalesce(d.text, ''), '\s+', ' ', 'g')) AS ref FROM pages JOIN documents d ON d.doc_id = try_cast(regexp_extract(url, '/(?:en|fr|de|es)/([0-9]+)', 1) AS BIGINT))"
EXTRACT = SQUEEZE.format(ENT.format(r"regexp_replace(regexp_replace(regexp_replace(html, '<(script|style)\b.*?</(script|style)>', ' ', 'gs'), '<!--.*?-->', ' ', 'gs'), '<[^>]*>', ' ', 'g')"))
_unread = r"NOT regexp_matches(coalesce(html, ''), '<article\b', 'i')"
_body = r"CASE WHEN regexp_matches(html, '<body\b', 'i') THEN regexp_extract(html, '<body\b[^>]*>(.*)', 1, 'is') ELSE coalesce(html, '') END"
_shown = SQUEEZE.format(ENT.format(rf"regexp_replace(regexp_replace(regexp_replace({_body}, '<script\b.*?</script>|<style\b.*?</style>|<title\b.*?</title>', ' ', 'gis'), '<!--.*?-->', ' ', 'gs'), '<[^>]*>', ' ', 'g')"))
#: Title and paragraphs of a page with an article, else what its body shows.
END_TO_END = f"""SELECT {{0}}page_id, string_agg(text, ' ' ORDER BY region_no) AS {{1}} FROM regions WHERE kind IN ('title', 'paragraph') AND page_id NOT IN (SELECT page_id FROM pages WHERE {_unread}) GROUP BY page_id
  UNION ALL SELECT {{0}}page_id, {_shown} FROM pages WHERE {_unread}"""
HYPS = f"""hyps AS (
  SELECT 'two_stage' AS parser, page_id, string_agg(text, ' ' ORDER BY region_no) AS hyp FROM regions WHERE kind = 'paragraph' GROUP BY page_id
  UNION ALL SELECT 'hybrid3', page_id, string_agg(text, ' ' ORDER BY region_no) FROM regions GROUP BY page_id
  UNION ALL SELECT 'end_to_end', page_id, string_agg(text, ' ' ORDER BY region_no) FROM regions WHERE kind IN ('title', 'paragraph') GROUP BY page_id
  UNION ALL SELECT 'extract', page_id, {EXTRACT} FROM pages),
pairs AS (SELECT parser, page_id AS id, ref, hyp FROM hyps JOIN truth USING (page_id))"""
#: The same with the end-to-end parser's whole pages.
HYPS_WHOLE = HYPS.replace("""SELECT 'end_to_end', page_id, string_agg(text, ' ' ORDER BY region_no) FROM regions WHERE kind IN ('title', 'paragraph') GROUP BY page_id""", END_TO_END.format("'end_to_end', ", "hyp"))


def bleu_sql(keys: str) -> str:
    """BLEU of ``pairs(parser, id, ref, hyp)`` grouped by ``keys``."""
    words = r"list_filter(regexp_split_to_array({0}, '\s+'), lambda x: x <> '')"
    gram = " UNION ALL ".join(f"SELECT parser, id, {n} AS n, unnest(list_transform(range(1, greatest(len(w) - {n - 1} + 1, 1)), lambda i: array_to_string(w[i : i + {n - 1}], ' '))) AS g FROM {{0}}" for n in range(1, 5))
    return f"""
rw AS (SELECT parser, id, {words.format('ref')} AS w FROM pairs), hw AS (SELECT parser, id, {words.format('hyp')} AS w FROM pairs),
rg AS (SELECT parser, id, n, g, count(*) AS c FROM ({gram.format('rw')}) GROUP BY ALL), hg AS (SELECT parser, id, n, g, count(*) AS c FROM ({gram.format('hw')}) GROUP BY ALL),
m AS (SELECT {keys}, n, sum(least(h.c, coalesce(r.c, 0))) AS matched, sum(h.c) AS produced FROM hg h LEFT JOIN rg r USING (parser, id, n, g) GROUP BY ALL),
len AS (SELECT {keys}, sum(len(rw.w)) AS r, sum(len(hw.w)) AS c FROM rw JOIN hw USING (parser, id) GROUP BY ALL),
logs AS (SELECT {keys}, sum(ln(matched / produced)) FILTER (matched > 0) AS l, count(*) FILTER (matched > 0) AS levels FROM m GROUP BY ALL)
SELECT {keys}, round(CASE WHEN coalesce(levels, 0) < 4 OR c = 0 THEN 0 ELSE (CASE WHEN c > r THEN 1.0 ELSE exp(1 - r / c) END) * exp(l / 4) END, 6)::DOUBLE AS bleu FROM len LEFT JOIN logs USING ({keys})"""


QUERIES = {
    "page_regions": q_regions, "region_census": q_census, "page_metadata": q_metadata, "parsed_pages": q_parsed_pages, "assembled_pages": q_assembled, "parsed_documents": q_parsed_documents,
    "parse_extract_baseline": _parser("extract"), "parse_hybrid3": _parser("hybrid3"), "parse_end_to_end": _parser("end_to_end"), "parse_scanline": _parser("scanline"),
    "parser_routes": q_failures, "parser_failures": q_failure_rate, "split_pages": q_split_pages, "parser_bleu": q_bleu, "parser_bleu_corpus": q_bleu_corpus,
    "parser_car_precision": q_car_precision, "parser_car_edit": q_car_edit, "parser_sample": q_sample, "page_assets": q_assets,
}
_squeezed_doc = r"trim(regexp_replace(coalesce(text, ''), '\s+', ' ', 'g'))"
ORACLES = {
    "page_regions": f"WITH {REGIONS} SELECT page_id, region_no, kind, role, text FROM regions",
    "region_census": f"WITH {REGIONS} SELECT kind, role, count(*) AS regions, count(DISTINCT page_id) AS pages FROM regions GROUP BY kind, role",
    "page_metadata": r"""SELECT page_id, 'lang' AS key, regexp_extract(html, '<html lang="([a-z]*)"', 1) AS value FROM pages
UNION ALL SELECT page_id, 'title', replace(replace(regexp_extract(html, '<title>(.*?)</title>', 1, 's'), '&quot;', '"'), '&amp;', '&') FROM pages
UNION ALL SELECT page_id, 'host', regexp_extract(url, '://([^/:]+)', 1) FROM pages
UNION ALL SELECT page_id, 'links', ((length(html) - length(replace(html, '<a ', ''))) / 3)::BIGINT::VARCHAR FROM pages
UNION ALL SELECT page_id, 'authors', array_to_string(list_concat(regexp_extract_all(html, '<meta name="author" content="([^"]*)"', 1), regexp_extract_all(html, '<[a-z0-9]+[^>]* class="byline"[^>]*>([^<]*)</', 1)), '; ') FROM pages
UNION ALL SELECT page_id, 'citations', array_to_string(list_concat(regexp_extract_all(html, '<cite[^>]*>([^<]*)</cite>', 1), regexp_extract_all(html, '(\[[0-9]{1,3}\])', 1)), '; ') FROM pages
UNION ALL SELECT page_id, 'references', array_to_string(regexp_extract_all(regexp_extract(html, '<ol class="references">(.*?)</ol>', 1, 's'), '<li>([^<]*)</li>', 1), '; ') FROM pages""",
    "parsed_pages": f"WITH {TRUTH} SELECT page_id, ref AS text FROM truth",
    "assembled_pages": f"WITH {TRUTH} SELECT page_id, ref AS text FROM truth",
    "parsed_documents": f"SELECT doc_id, {_squeezed_doc} AS full_text FROM documents WHERE doc_id IN (SELECT try_cast(regexp_extract(url, '/(?:en|fr|de|es)/([0-9]+)', 1) AS BIGINT) FROM pages)",
    "parse_extract_baseline": f"SELECT page_id, {EXTRACT} AS text FROM pages",
    "parse_hybrid3": f"WITH {REGIONS} SELECT page_id, string_agg(text, ' ' ORDER BY region_no) AS text FROM regions GROUP BY page_id",
    "parse_end_to_end": f"WITH {REGIONS} {END_TO_END.format('', 'text')}",
    "parse_scanline": f"SELECT page_id, {EXTRACT} AS text FROM pages",
    "parser_routes": r"SELECT CASE WHEN regexp_matches(regexp_replace(regexp_extract(html, '<article>(.*)</article>', 1, 's'), '<[^>]*>', '', 'g'), '\S') THEN 'extract' ELSE 'recognise' END AS route, count(*) AS pages FROM pages GROUP BY 1",
    "parser_failures": f"SELECT count(*) AS files, sum(({EXTRACT} = '')::INT)::BIGINT AS failed, round(avg(({EXTRACT} = '')::INT), 6) AS rate FROM pages",
    "split_pages": "SELECT doc_id, i::INT AS page_no, substr(text, i * 3000 + 1, 3000) AS text FROM (SELECT doc_id, text, unnest(range(0, greatest(ceil(length(text) / 3000)::INT, 1))) AS i FROM documents)",
    "parser_bleu": f"WITH {TRUTH}, pairs AS (SELECT 'extract' AS parser, page_id AS id, ref, {EXTRACT} AS hyp FROM pages JOIN truth USING (page_id)), {bleu_sql('id').replace('SELECT id, round', 'SELECT id AS page_id, round')}",
    "parser_bleu_corpus": f"WITH {REGIONS}, {TRUTH}, {HYPS_WHOLE}, {bleu_sql('parser')}",
    "parser_car_precision": f"""WITH {REGIONS}, {TRUTH}, {HYPS},
rc AS (SELECT parser, id, ch, count(*) AS c FROM (SELECT parser, id, unnest(string_split(ref, '')) AS ch FROM pairs) GROUP BY ALL),
hc AS (SELECT parser, id, ch, count(*) AS c FROM (SELECT parser, id, unnest(string_split({SQUEEZE.format('hyp')}, '')) AS ch FROM pairs) GROUP BY ALL),
v AS (SELECT parser, id, sum(least(h.c, coalesce(r.c, 0))) / sum(h.c) AS v FROM hc h LEFT JOIN rc r USING (parser, id, ch) GROUP BY parser, id)
SELECT parser, round(avg(round(v, 6)), 6) AS car FROM v GROUP BY parser""",
    "page_assets": f"WITH {REGIONS} SELECT page_id, 0::BIGINT AS assets, count(*) AS regions FROM regions GROUP BY page_id",
    "parser_sample": r"""WITH n AS (SELECT page_id, concat_ws('/', regexp_extract(html, '<html lang="([a-z]*)"', 1), substr(md5(regexp_extract(url, '://(?:[^/]*\.)?([a-z]+)\.[a-z]+(?:[:/?#]|$)', 1)), 1, 1)) AS stratum, md5(page_id::VARCHAR) AS h FROM pages),
r AS (SELECT *, row_number() OVER (PARTITION BY stratum ORDER BY h, page_id) AS r FROM n) SELECT page_id, stratum FROM r ORDER BY r, stratum LIMIT 100""",
}
