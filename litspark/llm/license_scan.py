"""Licence scans: sentences become known identifiers, identifier sequences meet ordered rules.

A text is cut into sentences (at line ends, and after ``. ! ? :`` before white
space, but not inside the announcement of a public identifier), each is normalised (lower case, runs of other characters than letters
and digits become one blank) and mapped to the identifier of the known licence
sentence that it is.  A text is also read with its lines joined, so that wrapped
sentences are found; the reading with more identifiers counts, by lines if equal.  The identifiers of a
text, in order, are matched against rules: a rule is a licence and identifiers
that must follow one another.

One pass of expressions over each row: no shuffle, no Python.

Edge cases: a null or empty text has no identifiers and no licence; repeated
sentences count each time in ``n_sentences`` but a licence is named once; texts
are read whole; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from litspark.llm.license_rules import ANNOUNCED, COVERED, RULES, SENTENCES, announced_sentences, named_sentences

#: Lower-case fragments of which every known sentence holds one (asserted below), to pass over all other text cheaply.
CUES = ("licens", "permission", "copyright notice", "warrant", "redistribut", "free software", "public domain", "contributors may be used")
WRAP = r"[ \t]*\n+[ \t]*"
SPLIT = r"\n+|(?<=[.!?:])[ \t]+"


def normalise(sentence: str) -> str:
    return re.sub(r"[^a-z0-9]+", " ", sentence.lower()).strip()


KNOWN = {normalise(s): i for i, s in SENTENCES.items()}
if len(KNOWN) < len(SENTENCES):
    raise ValueError("known sentences must differ")
KNOWN = {normalise(s): i for s, i in (named_sentences() | announced_sentences()).items()} | KNOWN
if not all(any(c in s for c in CUES) for s in KNOWN):
    raise ValueError("known sentences must each hold a cue")
if any(len(re.split(SPLIT, s)) > 1 for s in SENTENCES.values()):
    raise ValueError("known sentences must be single sentences")
if {i for _, _, ids in RULES for i in ids} - set(KNOWN.values()):
    raise ValueError("a rule names an unknown sentence")


def _normalised(sentence: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(sentence), "[^a-z0-9]+", " "))


def identifiers(text: Column) -> Column:
    """Identifiers of the known sentences of a text, in order."""
    table = F.create_map(*[F.lit(x) for pair in KNOWN.items() for x in pair])
    cue = "|".join(CUES)
    # an announcement and its value are one sentence
    text = F.regexp_replace(text, rf"(?i)({ANNOUNCED}):[ \t]+", "$1 ")

    def name(sentences: Column) -> Column:
        return F.filter(F.transform(sentences, lambda s: F.try_element_at(table, _normalised(s))), lambda i: i.isNotNull())

    by_line = F.split(text, SPLIT)
    unwrapped = F.split(F.regexp_replace(text, WRAP, " "), SPLIT)
    both = F.when(F.size(name(by_line)) >= F.size(name(unwrapped)), name(by_line)).otherwise(name(unwrapped))
    return F.when(F.lower(text).rlike(cue), both).otherwise(F.array().cast("array<string>"))


def _fits(joined: Column, ids: tuple[str, ...]) -> Column:
    return joined.rlike(",(?:[a-z0-9_]+,)*?".join(["(?:^|,)" + ids[0], *ids[1:]]) + "(?:,|$)")


def licences(ids: Column) -> tuple[Column, Column]:
    """(names of the rules that count, licences), both sorted arrays, for an array of identifiers."""
    joined = F.array_join(ids, ",")
    rules, names = [], []
    for licence in dict.fromkeys(name for _, name, _ in RULES):
        own = F.coalesce(*[F.when(_fits(joined, wanted), F.lit(rule)) for rule, name, wanted in RULES if name == licence])
        stronger = [s for w, s in COVERED if w == licence]
        for s in stronger:
            for _, _, wanted in [r for r in RULES if r[1] == s]:
                own = F.when(_fits(joined, wanted), F.lit(None)).otherwise(own)
        rules.append(own)
        names.append(F.when(own.isNotNull(), F.lit(licence)))
    return F.array_sort(F.array_compact(F.array(*rules))), F.array_sort(F.array_compact(F.array(*names)))


def license_report(docs: DataFrame) -> DataFrame:
    """One row per row of ``docs(doc_id, text)``: doc_id, n_sentences, sentence_ids, rules, licences (joined by commas)."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    named = docs.select(F.col("doc_id").cast("long").alias("doc_id"), identifiers(text).alias("ids"))
    rules, names = licences(F.col("ids"))
    some = F.size("ids") > 0
    listed = lambda c: F.when(some, F.array_join(c, ",")).otherwise(F.lit(""))
    return named.select("doc_id", F.size("ids").cast("long").alias("n_sentences"), F.array_join("ids", ",").alias("sentence_ids"), listed(rules).alias("rules"), listed(names).alias("licences"))


def oracle() -> str:
    """DuckDB SQL of ``license_report`` on ``documents``."""
    q = lambda s: "'" + s.replace("'", "''") + "'"
    table = ", ".join(f"({q(s)}, {q(i)})" for s, i in KNOWN.items())
    cut = lambda text: f"regexp_split_to_array(regexp_replace({text}, '([.!?:])[ \\t]+', '\\1' || chr(10), 'g'), '\\n+')"
    fit = lambda ids: "regexp_matches(sentence_ids, " + q(",(?:[a-z0-9_]+,)*?".join(["(?:^|,)" + ids[0], *ids[1:]]) + "(?:,|$)") + ")"
    rules, names = [], []
    for licence in dict.fromkeys(name for _, name, _ in RULES):
        own = "CASE " + " ".join(f"WHEN {fit(w)} THEN {q(r)}" for r, n, w in RULES if n == licence) + " END"
        for s in [s for w, s in COVERED if w == licence]:
            own = "CASE " + " ".join(f"WHEN {fit(w)} THEN NULL" for _, n, w in RULES if n == s) + f" ELSE {own} END"
        rules.append(own)
        names.append(f"CASE WHEN ({own}) IS NOT NULL THEN {q(licence)} END")
    listed = lambda cases: f"coalesce(array_to_string(list_sort(list_filter([{', '.join(cases)}], lambda x: x IS NOT NULL)), ','), '')"
    return f"""
WITH known(sentence, id) AS (VALUES {table}),
texts AS (SELECT doc_id, row_number() OVER () AS r, regexp_replace(coalesce(text, ''), '({ANNOUNCED}):[ \\t]+', '\\1 ', 'gi') AS t FROM documents),
cuts AS (
  SELECT r, 0 AS way, {cut('t')} AS s FROM texts
  UNION ALL SELECT r, 1, {cut("regexp_replace(t, '[ \\t]*\\n+[ \\t]*', ' ', 'g')")} FROM texts),
spots AS (SELECT r, way, unnest(s) AS s, generate_subscripts(s, 1) AS place FROM cuts),
named AS (SELECT r, way, place, id FROM spots JOIN known ON trim(regexp_replace(lower(s), '[^a-z0-9]+', ' ', 'g')) = sentence),
listed AS (SELECT r, way, count(*) AS n, string_agg(id, ',' ORDER BY place) AS ids FROM named GROUP BY r, way),
best AS (SELECT r, max_by(ids, n * 2 - way) AS sentence_ids, max_by(n, n * 2 - way) AS n FROM listed GROUP BY r),
every AS (SELECT doc_id, coalesce(n, 0)::BIGINT AS n_sentences, coalesce(sentence_ids, '') AS sentence_ids FROM texts LEFT JOIN best USING (r))
SELECT doc_id, n_sentences, sentence_ids, {listed(rules)} AS rules, {listed(names)} AS licences FROM every
"""
