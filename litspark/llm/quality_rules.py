"""Quality rules: fixed base rules, then robust multivariate outliers per language and source.

Every text becomes a vector of transformed statistics in fixed point, so sums are
exact integers and no result depends on the order of rows.  The vectors are
written once; all that follows reads that narrow table.  For each group
(language, source) the minimum-covariance-determinant estimate is searched for:

1. ``STARTS`` starts per group, each the mean and covariance of ``DRAWN`` rows,
   the ones with the smallest of as many hashes.
2. Concentration steps for all starts at once: distances to the last estimate,
   the share ``COVER`` of the rows with the smallest ones, their mean and
   covariance.  Distances are ranked by a histogram, so a step is one aggregation
   of mergeable counts and moments; of the bin that the share ends in, rows count
   by the fraction that is still needed, so that every estimate covers exactly
   the same number of rows and their determinants can be compared.
3. The start with the smallest determinant wins, gets further steps, and then one
   reweighting step over the rows within the 97.5 % quantile of its distances.

A row whose squared Mahalanobis distance to that estimate exceeds ``CUTOFF`` is
rejected.  Statistics that are equal in most rows have no spread of their own, so
the covariance gets a fixed diagonal target (``FLOORS``), as regularised
estimates of this kind do.

Groups of fewer than ``LEAST`` rows are pooled by language, then over all; a pool
still smaller gives no verdict and its rows are kept.

Everything is DataFrame expressions; texts are read once.  Per group only bins
and estimates are shuffled.

Edge cases: a null or empty text has no words and fails the base rule; null
language or source is a value of its own; rows repeated are judged alike and all
count; an empty table gives an empty result; clashing extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from litspark.llm.common import BROADCAST_ROWS, Scratch

SYMBOLS = "#*$%&|<>"
BLANKS = " \t\n\x0b\x0c\r"
WINDOW = 8
MIN_WORDS = 20
MAX_REPEATED = 30
COVER = 0.75
#: Starts per group, rows of each, steps of all starts, and further steps of the best one.
STARTS, DRAWN, FIRST_STEPS, LAST_STEPS = 6, 5, 2, 3
#: Bins of a doubling of one plus the squared distance.
BINS = 12
#: The 97.5 % quantile of chi-squared with four degrees of freedom, and the share of it.
NEAR, NEAR_SHARE = 11.143287, 0.975
LEAST = 40
#: The 1 - 1e-4 quantile of chi-squared with four degrees of freedom.
CUTOFF = 23.513
SCALE = 4096
#: Standard deviations that a group is granted at least: log word length, log symbols, log repeated lines, repeated words.
FLOORS = (0.035, 0.25, 0.6, 0.1)
#: Words of the usual length that each text is given, so that short texts do not stand out by chance.
PRIOR_WORDS, PRIOR_LENGTH = 30, 5
VECTOR = ("x0", "x1", "x2", "x3")
#: An estimate: the means, then the lower triangle of the inverse Cholesky factor of the covariance.
ESTIMATE = [*[f"m{i}" for i in range(len(VECTOR))], *[f"w{i}{j}" for i in range(len(VECTOR)) for j in range(i + 1)]]


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use(value)`` with ``value`` evaluated once, however often it is used inside lambdas."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def repeated_words(words: Column, width: int = WINDOW) -> Column:
    """Number of words in windows of ``width`` words that occur twice or more in the array."""

    def covered(spots: Column) -> Column:
        spans = F.transform(spots, lambda p, i: F.least(F.lit(width), F.coalesce(F.get(spots, i + 1) - p, F.lit(width))))
        return F.aggregate(spans, F.lit(0), lambda a, b: a + b)

    def twice(ranked: Column) -> Column:
        same = lambda e, i: (e["h"] == F.get(ranked, i - 1)["h"]) | (e["h"] == F.get(ranked, i + 1)["h"])
        marked = F.filter(F.transform(ranked, lambda e, i: F.when(F.when(i == 0, e["h"] == F.get(ranked, i + 1)["h"]).otherwise(F.coalesce(same(e, i), e["h"] == F.get(ranked, i - 1)["h"])), e["p"])), lambda p: p.isNotNull())
        return let(F.sort_array(marked), covered)

    def of_hashes(grams: Column) -> Column:
        ranked = F.sort_array(F.transform(grams, lambda h, i: F.struct(h.alias("h"), i.alias("p"))))
        return F.when(F.size(F.array_distinct(grams)) == F.size(grams), F.lit(0)).otherwise(let(ranked, twice))

    def of_words(hashes: Column) -> Column:
        grams = F.transform(F.slice(hashes, F.lit(1), F.size(hashes) - (width - 1)), lambda h, i: F.xxhash64(h, *[F.get(hashes, i + j) for j in range(1, width)]))
        return let(grams, of_hashes)

    hashed = F.transform(words, lambda w: F.xxhash64(w))
    return F.when(F.size(words) <= width, F.lit(0)).otherwise(let(hashed, of_words)).cast("long")


def statistics(text: Column) -> dict[str, Column]:
    """The base statistics of a text (never null)."""
    trimmed = F.btrim(text, F.lit(BLANKS))
    words = F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, "[ \t-\r]+"))
    lines = F.filter(F.split(text, "\n"), lambda x: F.btrim(x, F.lit(BLANKS)) != "")
    both = let(words, lambda w: F.struct(F.size(w).cast("long").alias("n"), repeated_words(w).alias("r")))
    return {
        "words": both,
        "word_chars": F.char_length(F.translate(text, BLANKS, "")).cast("long"),
        "n_symbols": (F.char_length(text) - F.char_length(F.translate(text, SYMBOLS, ""))).cast("long"),
        "n_dup_lines": let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long"),
    }


def document_statistics(docs: DataFrame) -> DataFrame:
    """doc_id, grp columns, the base statistics, base_failed and the vector in fixed point."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    named = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.xxhash64(F.col("text").cast("string")).alias("tag"),
        F.coalesce(F.concat(F.lit("="), F.col("lang").cast("string")), F.lit("?")).alias("lang"),
        F.coalesce(F.concat(F.lit("="), F.col("source").cast("string")), F.lit("?")).alias("source"),
        *[c.alias(n) for n, c in statistics(text).items()],
    )
    flat = named.select("doc_id", "tag", "lang", "source", F.col("words.n").alias("n_words"), "word_chars", "n_symbols", "n_dup_lines", F.col("words.r").alias("n_repeat_words"))
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEATED * F.col("n_words"))
    n = F.greatest(F.col("n_words"), F.lit(1))
    vector = (
        F.log((F.col("word_chars") + PRIOR_WORDS * PRIOR_LENGTH) / (n + PRIOR_WORDS)),
        F.log(1 + 100 * F.col("n_symbols") / n),
        F.log(1 + 100 * F.col("n_dup_lines") / n),
        F.col("n_repeat_words") / n,
    )
    return flat.select("*", failed.alias("base_failed"), *[F.round(v * SCALE).cast("long").alias(x) for x, v in zip(VECTOR, vector)])


def _chi2_cdf(x: float, dof: int) -> float:
    """Chi-squared distribution for an even number of degrees of freedom."""
    half = x / 2
    return 1 - math.exp(-half) * sum(half**k / math.factorial(k) for k in range(dof // 2))


def consistency(cover: float, dof: int = len(VECTOR)) -> float:
    """Factor that makes the covariance of the covered share consistent at a normal distribution."""
    low, high = 0.0, 200.0
    for _ in range(100):
        mid = (low + high) / 2
        low, high = (mid, high) if _chi2_cdf(mid, dof) < cover else (low, mid)
    return cover / _chi2_cdf(low, dof + 2)


def _total(terms: Iterable[str]) -> str:
    """SQL of a sum in this order, zero without terms."""
    return " + ".join(["0.0D", *terms])


def _double(value: float) -> str:
    """SQL of a double."""
    return f"{float(value)!r}D"


def _estimate(moments: DataFrame, factor: float, *keys: str) -> DataFrame:
    """keys, m0.. , the rows w00.. of the inverse Cholesky factor and the log determinant, from n and sums s_i, s_ij."""
    p = range(len(VECTOR))
    pairs = [(i, j) for i in p for j in range(i + 1)]
    spread = {(i, j): f"(s{i}{j} / n / {SCALE} / {SCALE} - m{i} * m{j})" for i, j in pairs}
    made = {f"m{i}": f"s{i} / n / {SCALE}" for i in p}
    for i, j in pairs:
        made[f"v{i}{j}"] = f"greatest({spread[i, i]}, 0.0D) * {_double(factor)} + {_double(FLOORS[i] ** 2)}" if i == j else f"{spread[i, j]} * {_double(factor)}"
    for j in p:
        dot = {i: _total(f"l{i}{k} * l{j}{k}" for k in range(j)) for i in range(j, len(VECTOR))}
        made[f"l{j}{j}"] = f"sqrt(greatest(v{j}{j} - ({dot[j]}), {_double(FLOORS[j] ** 2 / 4)}))"
        made |= {f"l{i}{j}": f"(v{i}{j} - ({dot[i]})) / l{j}{j}" for i in range(j + 1, len(VECTOR))}
    for i in p:
        made |= {f"w{i}{j}": f"-({_total(f'l{i}{k} * w{k}{j}' for k in range(j, i))}) / l{i}{i}" for j in range(i)} | {f"w{i}{i}": f"1 / l{i}{i}"}
    made["logdet"] = _total(f"ln(l{i}{i})" for i in p)
    # later columns of this list build on earlier ones
    out = moments.withColumn("n", F.col("n").cast("double")).selectExpr(*keys, *[f"{value} as {name}" for name, value in made.items()])
    return out.select(*keys, *ESTIMATE, "logdet")


def _distance() -> Column:
    """Squared Mahalanobis distance of a row's vector to the estimate beside it; null without one."""
    off = [f"({x} / {_double(SCALE)} - m{i})" for i, x in enumerate(VECTOR)]
    return F.expr(_total(f"pow({_total(f'w{i}{k} * {off[k]}' for k in range(i + 1))}, 2.0D)" for i in range(len(VECTOR))))


def _sums() -> list[Column]:
    once, twice = {f"s{i}": x for i, x in enumerate(VECTOR)}, {f"s{i}{j}": f"{VECTOR[i]} * {VECTOR[j]}" for i in range(len(VECTOR)) for j in range(i + 1)}
    return [F.count("*").alias("n"), *[F.expr(f"sum({value}) as {name}") for name, value in (once | twice).items()]]


def _starts(rows: DataFrame, scratch: Scratch, near: Callable[[DataFrame], DataFrame], starts: int) -> DataFrame:
    """Estimates (grp, start) of the rows that hold the smallest of ``DRAWN`` hashes for each start."""
    hashes = [f"xxhash64({', '.join(VECTOR)}, tag, {i})" for i in range(starts * DRAWN)]
    lows = scratch.write(rows.groupBy("grp").agg(*[F.expr(f"min({h}) as h{i}") for i, h in enumerate(hashes)]), "draws")
    drawn = ", ".join(f"if({h} = h{i}, {i // DRAWN}, null)" for i, h in enumerate(hashes))
    # of rows that are equal in all that is hashed one stands for all
    taken = rows.join(near(lows), "grp").selectExpr("grp", "tag", *VECTOR, f"explode(array_compact(array({drawn}))) as start").distinct()
    return scratch.write(_estimate(taken.groupBy("grp", "start").agg(*_sums()), 1.0, "grp", "start"), "estimate")


def _step(rows: DataFrame, estimate: DataFrame, cover: float) -> DataFrame:
    """One concentration step of every (grp, start) of ``estimate``."""
    parts = rows.join(estimate, "grp").select("grp", "start", F.floor(BINS * F.log2(1 + _distance())).cast("int").alias("bin"), *VECTOR).groupBy("grp", "start", "bin").agg(*_sums())
    names = [c for c in parts.columns if c not in ("grp", "start", "bin")]
    within = Window.partitionBy("grp", "start")
    before = F.coalesce(F.sum("n").over(within.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranked = parts.withColumns({"before": before, "need": F.ceil(F.lit(cover) * F.sum("n").over(within))})
    covered = ranked.where("before < need").selectExpr("grp", "start", *[f"{c} * least(1.0D, (need - before) / n) as {c}" for c in names])
    # in the order of the bins, so that the sums of fractions do not depend on how rows are dealt
    listed = covered.groupBy("grp", "start").agg(F.sort_array(F.collect_list(F.struct(*names))).alias("bins"))
    totals = [f"aggregate(bins.{c}, 0.0D, (a, b) -> a + b) as {c}" for c in names]
    return _estimate(listed.selectExpr("grp", "start", *totals), consistency(cover), "grp", "start")


def mcd_estimates(rows: DataFrame, groups: int, scratch: Scratch, cover: float = COVER, starts: int = STARTS) -> DataFrame:
    """Minimum-covariance-determinant estimates of ``rows(grp, tag, x0..)`` per group, ``groups`` of them: means and inverse Cholesky factors."""
    near = (lambda df: F.broadcast(df)) if groups * starts <= BROADCAST_ROWS else (lambda df: df)
    estimate = _starts(rows, scratch, near, starts)
    for _ in range(FIRST_STEPS):
        estimate = scratch.write(_step(rows, near(estimate), cover), "estimate")
    best = F.min_by(F.struct("start", *ESTIMATE), F.struct("logdet", "start")).alias("best")
    estimate = estimate.groupBy("grp").agg(best).select("grp", "best.*")
    for _ in range(LAST_STEPS):
        estimate = scratch.write(_step(rows, near(estimate), cover), "estimate")
    inside = rows.join(near(estimate), "grp").where(_distance() <= NEAR).groupBy("grp").agg(*_sums())
    return scratch.write(_estimate(inside, consistency(NEAR_SHARE), "grp"), "estimate")


def _grouped(stats: DataFrame, least: int) -> DataFrame:
    """Rows with ``grp``: the group that they are estimated with, null if even the pool of all is too small."""
    usable = stats.where("not base_failed")
    pair = usable.groupBy("lang", "source").agg(F.count("*").alias("c_pair"))
    pooled = pair.where(F.col("c_pair") < least)
    by_lang = pooled.groupBy("lang").agg(F.sum("c_pair").alias("c_lang"))
    # pooled languages that are small themselves share one key, so that their sum is a plain aggregate
    rest = by_lang.where(F.col("c_lang") < least).groupBy(F.lit("all").alias("every")).agg(F.sum("c_lang").alias("c_all"))
    named = pair.withColumn("every", F.lit("all")).join(by_lang, "lang", "left").join(rest, "every", "left")
    grp = (
        F.when(F.col("c_pair") >= least, F.to_json(F.array("lang", "source")))
        .when(F.col("c_lang") >= least, F.to_json(F.array("lang")))
        .when(F.col("c_all") >= least, F.lit("all"))
    )
    return named.select("lang", "source", grp.alias("grp"))


def quality_verdicts(docs: DataFrame, cover: float = COVER, cutoff: float = CUTOFF, least: int = LEAST) -> DataFrame:
    """One row per row of ``docs(doc_id, text, lang, source)``: the statistics, base_failed, distance2 and kept.

    ``tag`` is the 64-bit hash of the text, which with doc_id names the row.
    """
    scratch = Scratch(docs.sparkSession, "quality")
    stats = scratch.write(document_statistics(docs), "stats")
    groups = scratch.write(_grouped(stats, least), "groups")
    named, judging = groups.agg(F.count("*"), F.count_distinct("grp")).first()
    rows = stats.join(F.broadcast(groups) if named <= BROADCAST_ROWS else groups, ["lang", "source"], "left")
    estimate = mcd_estimates(rows.where("not base_failed and grp is not null").select("grp", "tag", *VECTOR), judging, scratch, cover)
    judged = rows.join(F.broadcast(estimate) if judging <= BROADCAST_ROWS else estimate, "grp", "left").withColumn("d2", _distance())
    kept = ~F.col("base_failed") & (F.coalesce(F.col("d2"), F.lit(0.0)) <= cutoff)
    return judged.select("doc_id", "tag", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", F.round("d2", 6).alias("distance2"), kept.alias("kept"))
