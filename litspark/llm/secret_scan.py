"""Secret scans: candidates by rule, false positives removed by a random forest.

Candidates are the runs of at least ``LEAST`` letters, digits, ``_ + / -`` (and
closing ``=``) that hold a digit, all of each word, also where dots join them,
and the values that follow a word for a credential: in the same word, or of
``SHORT`` characters or more where one of the two words before is one.  Each one
gets its length, character transitions, dictionary coverage (whole words of a
public vocabulary, and common fragments), path and neighbouring words; a forest
trained on labelled findings (``secret_forest``) decides.  Findings are replaced
in the text.

The scan is one pass of expressions over each row: no shuffle, no Python.

Edge cases: a null or empty text has no candidates and stays as it is; very long
texts are scanned whole; repeated findings count each time; rows are independent,
so repeated rows and an empty table need no care; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from litspark.llm.common import fresh
from litspark.llm.quality_rules import BLANKS, let
from litspark.llm.secret_forest import FEATURES, KEY_WORDS, dictionary, features, load, probability

LEAST = 16
SHORT = 8
THRESHOLD = 0.5
REDACTED = "[SECRET]"
#: A run, with closing = unless a value follows, so that the name of an assignment has none.
BODY = r"([A-Za-z0-9_+/-]{%d,}(?:={1,2}(?![A-Za-z0-9_=\"']))?)" % LEAST
_NAMED = r"(?i)(?:token|secret|passw|pwd|api_?key|access_?key|private_?key|credential|bearer)[A-Za-z_-]{0,20}"
#: Values behind a credential's name: up to the closing quote, or up to what ends a field.
QUOTED = _NAMED + r"[\"']?[=:][\"']([^\s\"']{8,})[\"']"
VALUE = _NAMED + r"[\"']?[=:]([^\s\"',;&?#{}\[\]<>]{8,})"
JOINED = r"([A-Za-z0-9_+/-]{%d,}(?:\.[A-Za-z0-9_+/-]{%d,})+={0,2})" % (LEAST, LEAST)
LOOSE = r"([^\s\"',;]{%d,})" % SHORT
#: Where the next field of a query string starts.
FIELD = r"[?&](?=[A-Za-z0-9_.-]+=)"


def _bodies(word: Column, near: Column) -> Column:
    """All candidates inside a word; ``near`` tells that a word before it names a credential."""
    every = lambda w, pattern: F.regexp_extract_all(w, F.lit(pattern), F.lit(1))

    def of(fields: Column) -> Column:
        named = F.concat(every(fields, QUOTED), every(fields, VALUE))
        runs = F.concat(F.filter(every(fields, BODY), lambda r: r.rlike("[0-9]")), F.when(fields.contains("."), every(fields, JOINED)).otherwise(F.array().cast("array<string>")))
        own = F.concat(named, F.filter(runs, lambda r: ~F.exists(named, lambda v: v.contains(r))))
        return F.when((F.size(own) == 0) & near, every(fields, LOOSE)).otherwise(own)

    return let(F.regexp_replace(word, FIELD, " "), of)


def candidates(text: Column) -> Column:
    """array<struct<body, before, second, whole>> of a text."""
    trimmed = F.btrim(text, F.lit(BLANKS))

    def of(words: Column) -> Column:
        at = lambda i: F.coalesce(F.when(i >= 0, F.get(words, i)), F.lit(""))
        told = lambda i: F.concat_ws(" ", at(i - 2), at(i - 1)).rlike(KEY_WORDS)
        short = lambda w, i: (F.length(w) >= SHORT) & (w.rlike("[0-9]") | at(i - 1).rlike("[=:]$")) & told(i)
        spots = F.transform(words, lambda w, i: F.when((F.length(w) >= LEAST) & w.rlike(r"[0-9]"), i).when((F.length(w) >= 12) & w.rlike(r"[=:]"), i).when(short(w, i), i))
        spots = F.filter(spots, lambda i: i.isNotNull())
        made = F.flatten(F.transform(spots, lambda i: F.transform(_bodies(F.get(words, i), told(i)), lambda b: F.struct(b.alias("body"), at(i - 1).alias("before"), at(i - 2).alias("second"), F.get(words, i).alias("whole")))))
        return F.filter(made, lambda c: (c["body"] != "") & (c["body"].rlike("[0-9]") | F.concat_ws(" ", c["before"], c["whole"]).rlike(KEY_WORDS)))

    return let(F.split(trimmed, "[ \t-\r]+"), of)


def scored(found: Column, forest: list) -> Column:
    """array<struct<body, score>>."""
    known = dictionary()
    names = lambda c: [v.alias(n) for n, v in features(c["body"], c["before"], c["second"], c["whole"], known).items()]
    ready = F.transform(found, lambda c: F.struct(c["body"].alias("body"), *names(c)))
    return F.transform(ready, lambda c: F.struct(c["body"].alias("body"), probability(forest, lambda n: c[n]).alias("score")))


def scan_secrets(docs: DataFrame, threshold: float = THRESHOLD, forest: list | None = None) -> DataFrame:
    """All columns of ``docs`` and candidates, findings (array<string>) and redacted (the text without them).

    A column of ``docs`` that has one of these names is replaced.
    """
    forest = load() if forest is None else forest
    if {n for t in forest for n in _used(t)} - set(FEATURES):
        raise ValueError("the forest asks for unknown features")
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    (score,) = fresh(docs, "judged")
    found = docs.withColumn("candidates", candidates(text))
    # a plan of its own, so that the array is not computed again inside each later expression
    judged = found.withColumn(score, scored(F.col("candidates"), forest))
    hits = F.transform(F.filter(score, lambda c: c["score"] >= threshold), lambda c: c["body"])
    marked = judged.withColumn("findings", hits)
    longest_first = F.array_sort(F.array_distinct("findings"), lambda a, b: F.length(b) - F.length(a))
    cleaned = F.aggregate(longest_first, F.col("text").cast("string"), lambda t, s: F.replace(t, s, F.lit(REDACTED)))
    return marked.withColumn("redacted", F.when(F.size("findings") == 0, F.col("text").cast("string")).otherwise(cleaned)).drop(score)


def _used(node) -> set[str]:
    return {node[0]} | _used(node[2]) | _used(node[3]) if isinstance(node, list) else set()


def secret_report(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """One row per row of ``docs(doc_id, text)``: doc_id, n_candidates, n_findings, findings, redacted_sha256."""
    done = scan_secrets(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), threshold)
    return done.select(
        "doc_id",
        F.size("candidates").cast("long").alias("n_candidates"),
        F.size("findings").cast("long").alias("n_findings"),
        F.array_join("findings", " ").alias("findings"),
        F.sha2(F.coalesce("redacted", F.lit("")), 256).alias("redacted_sha256"),
    )
