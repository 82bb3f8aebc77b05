"""Training of the random forest that tells secrets from look-alikes, and its form as expressions.

``train`` grows a forest with Spark's own learner on labelled findings; the
result is plain nested lists, kept in ``secret_forest.json`` and compiled to
column expressions by ``probability``.  ``python -m litspark.llm.secret_forest``
writes the file anew.
"""

from __future__ import annotations

import json
import random
from functools import lru_cache
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

FEATURES = ("length", "switches", "digits", "uppers", "hexes", "distinct", "words", "dictionary", "path", "key_word", "assigned", "quoted", "code_word")
FILE = Path(__file__).with_name("secret_forest.json")
#: Bound of the labelled sample that a forest is fitted on.
SAMPLE_ROWS = 6000
TREES, DEPTH, SEED = 15, 6, 7
# Common fragments of words in the languages of the corpus, and the words that stand by credentials or by harmless codes.
FRAGMENTS = "tion|ment|ing|the|and|ent|ere|est|ion|que|eau|sch|ich|ein|und|ver|ung|heit|keit|able|ble|ous|ado|mente|eur|oire|user|name|data|test|file|path|value|index|class|error|config|example|image|page|item"
KEY_WORDS = r"(?i)token|secret|passw|pwd|api[_-]?key|apikey|access[_-]?key|private|credential|bearer|auth"
CODE_WORDS = r"(?i)commit|sha|md5|checksum|hash|uuid|guid|isbn|order|invoice|revision|build|version|card|account|phone|id"


#: Whole words of a public vocabulary, the most frequent first, that make the dictionary, and the letters that a word has at least.
DICTIONARY_WORDS, WORD_LETTERS = 6000, 4


@lru_cache(maxsize=4)
def dictionary(path: str | None = None) -> str:
    """Words between blanks: the whole lower-case words among the first tokens of the vocabulary at ``path``."""
    from litspark.llm.bpe import vocabulary_file

    known = json.loads(vocabulary_file(path))["model"]["vocab"]
    starts = "\u0120"  # stands for the blank before a word
    words = [t[1:] for t, _ in sorted(known.items(), key=lambda x: x[1]) if t.startswith(starts) and len(t) > WORD_LETTERS and t[1:].isascii() and t[1:].isalpha() and t[1:].islower()]
    return " " + " ".join(words[:DICTIONARY_WORDS]) + " "


def labelled_findings(count: int = SAMPLE_ROWS, seed: int = SEED) -> list[tuple[str, str, str, str, int]]:
    """(candidate, word before, second word before, whole word, label): credentials in the usual forms, and what is taken for them."""
    rng = random.Random(seed)
    hexes, alnum = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    syllables = "th er in on an re ti es en at ou ed nd ha it sh ie ch ung ein que eau ment tion pour ado llo rra cion".split()
    keys = "token secret password passwd api_key apikey access_key client_secret private_key auth_token TOKEN SECRET_KEY Bearer credential".split()
    codes = "commit sha md5 checksum order invoice revision build uuid guid isbn card account id version hash".split()
    common = dictionary().split()[:2000]
    draw = lambda letters, n: "".join(rng.choice(letters) for _ in range(n))
    word = lambda: "".join(rng.choice(syllables) for _ in range(rng.randint(1, 4)))
    out = []
    while len(out) < count:
        secret = rng.random() < 0.5
        if secret:
            kind = rng.randrange(5)
            body = (draw(hexes, rng.choice((32, 40, 48, 64))), draw(alnum, rng.randint(20, 44)), draw(alnum + "+/", rng.choice((40, 43, 64))) + "=" * rng.randint(0, 1), rng.choice(("AKIA", "ghp_", "sk_live_", "xoxb-")) + draw(alnum, rng.randint(16, 36)), draw(alnum + "_-", rng.randint(18, 40)))[kind]
            if rng.random() < 0.1:
                body = body.upper()
            if rng.random() < 0.15:
                body = draw(alnum + "_-", rng.randint(8, 15)) + rng.choice("0123456789")
            key, host = rng.choice(keys), f"https://{word()}.example/{word()}"
            before, second, form = rng.choice((
                ("=", key, '"%s"'), (":", key, "%s"), (key + ":", word(), "%s"), (key, word(), "%s"), (word(), word(), key + "=%s"), ("=", key, "'%s',"),
                (word(), word(), f'{{"{key}":"%s"}}'), (word(), word(), f'{{"{word()}":"{word()}","{key}":"%s","{word()}":1}}'), (word(), word(), f"{host}?{key}=%s"), (word(), word(), f"{host}?{word()}={word()}&{key}=%s&{word()}=1"),
                ("export", word(), f"{key.upper()}=%s"), (word(), word(), f"{key}:%s"), ("Authorization:", "-H", f"Bearer=%s"), (word(), word(), f"--{key}=%s"),
            ))
            if kind == 3 and rng.random() < 0.5:
                before, second, form = word(), word(), "%s"
        else:
            kind = rng.randrange(11)
            body = (
                draw("0123456789", rng.choice((16, 16, 17, 19, 20))), "".join(word() for _ in range(6)) + str(rng.randint(0, 99)), "/".join(word() for _ in range(5)) + f"/{rng.randint(1, 999)}",
                draw(hexes, 40), "-".join(draw(hexes, n) for n in (8, 4, 4, 4, 12)), "_".join(word() for _ in range(5)) + str(rng.randint(1, 9)), rng.choice("x0a1") * rng.randint(16, 40) + "1", f"{word()}-{rng.randint(2000, 2030)}-{rng.randint(10, 12)}-{rng.randint(10, 30)}-{word()}{word()}",
                draw(alnum + "+/", rng.choice((43, 86))) + "==", "_".join(rng.choice(common) for _ in range(rng.randint(3, 5))) + str(rng.randint(1, 9)), "-".join(rng.choice(common) for _ in range(4)) + f"-{rng.randint(10, 999)}",
            )[kind]
            before, second, form = rng.choice(((word(), word(), "%s"), (rng.choice(codes), word(), "%s"), (word() + ",", word(), "(%s)"), ("=", rng.choice(codes), '"%s"'), (word(), word(), "https://host.example/%s"), (rng.choice(codes) + ":", word(), "%s")))
            if rng.random() < 0.3:
                code, host = rng.choice(codes), f"https://{word()}.example"
                before, second, form = word(), word(), rng.choice((f'{{"{code}":"%s"}}', f'{{"token":"{word()}","{code}":"%s"}}', f"{host}/{word()}?{code}=%s", f"{host}/{word()}/%s", f"{code}=%s", f'"{code}":"%s",'))
            if kind == 8 and form == "%s":
                before, form = word(), rng.choice(('"integrity":"sha512-%s",', "data:image/png;base64,%s", "checksum=%s"))
            elif kind >= 9 and rng.random() < 0.5:
                before, second, form = rng.choice((("=", rng.choice(keys), "%s"), (rng.choice(keys) + ":", word(), "%s"), (word(), word(), rng.choice(keys) + "=%s")))
            if kind == 3 and form == "%s" and before not in codes:
                before = rng.choice(codes)
        end = rng.choice(("", "", "", ",", ".", "!!", "###"))
        out.append((body, before, second, form % body + end, int(secret)))
    return out


def features(body: Column, before: Column, second: Column, whole: Column, words: str | None = None) -> dict[str, Column]:
    """Numbers of a candidate: its length, character transitions, dictionary coverage, path and neighbouring words.

    The name right before a candidate in its word speaks for it alone; without
    one, the words before do.
    """
    n = F.greatest(F.length(body), F.lit(1)).cast("double")
    share = lambda letters: F.length(F.regexp_replace(body, f"[^{letters}]", "")) / n
    ahead = F.substring(whole, F.lit(1), F.greatest(F.instr(whole, body) - 1, F.lit(0)))
    own_key = F.regexp_extract(ahead, r"([A-Za-z0-9_.-]{2,40})[\"']?[=:][\"']?$", 1)
    near = F.when(own_key != "", own_key).otherwise(F.concat_ws(" ", second, before, ahead))
    runs = F.regexp_extract_all(F.lower(F.regexp_replace(body, "([a-z])([A-Z])", "$1 $2")), F.lit("([a-z]{%d,})" % WORD_LETTERS), F.lit(1))
    known = F.filter(runs, lambda r: F.contains(F.lit(words or dictionary()), F.concat(F.lit(" "), r, F.lit(" "))))
    return {
        "length": n,
        "switches": F.regexp_count(body, F.lit("[a-z]+|[A-Z]+|[0-9]+|[^a-zA-Z0-9]+")) / n,
        "digits": share("0-9"),
        "uppers": share("A-Z"),
        "hexes": share("0-9a-fA-F"),
        "distinct": F.size(F.array_distinct(F.split(body, ""))) / n,
        "words": 1 - F.length(F.regexp_replace(F.lower(body), FRAGMENTS, "")) / n,
        "dictionary": F.length(F.array_join(known, "")) / n,
        "path": (F.length(body) - F.length(F.translate(body, "/", ""))).cast("double") + F.when(ahead.contains("://") & (own_key == ""), 5.0).otherwise(0.0),
        "key_word": near.rlike(KEY_WORDS).cast("double"),
        "assigned": (before.rlike(r"[=:]$") | (own_key != "")).cast("double"),
        "quoted": whole.rlike("[\"']").cast("double"),
        "code_word": near.rlike(rf"(?i)(?<![a-z])({CODE_WORDS[4:]})(?![a-z])").cast("double"),
    }


def train(spark: SparkSession, rows: list[tuple[str, str, str, str, int]], trees: int = TREES, depth: int = DEPTH, seed: int = SEED) -> list:
    """Forest as nested lists: a leaf is a probability, a node is [feature, threshold, left, right]."""
    from pyspark.ml.classification import RandomForestClassifier
    from pyspark.ml.feature import VectorAssembler

    if len(rows) > SAMPLE_ROWS:
        raise ValueError(f"a forest is fitted on at most {SAMPLE_ROWS} labelled findings")
    df = spark.createDataFrame(rows, "body string, before string, second string, whole string, label int").coalesce(1)
    df = df.select("label", *[c.alias(n) for n, c in features(*(F.col(c) for c in ("body", "before", "second", "whole"))).items()])
    ready = VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(df)
    model = RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=seed, featureSubsetStrategy="sqrt").fit(ready)

    def plain(node) -> list | float:
        if node.numDescendants() == 0:
            stats = node.impurityStats().stats()
            return round(stats[1] / (stats[0] + stats[1]), 6)
        split = node.split()
        return [FEATURES[split.featureIndex()], round(split.threshold(), 6), plain(node.leftChild()), plain(node.rightChild())]

    return [plain(tree._call_java("rootNode")) for tree in model.trees]


def load() -> list:
    return json.loads(FILE.read_text())


def probability(forest: list, value) -> Column:
    """Mean over the trees; ``value(name)`` gives a feature's column."""

    def grow(node) -> Column:
        if not isinstance(node, list):
            return F.lit(float(node))
        name, bound, left, right = node
        return F.when(value(name) <= bound, grow(left)).otherwise(grow(right))

    return sum((grow(t) for t in forest[1:]), grow(forest[0])) / len(forest)


def accuracy(spark: SparkSession, forest: list, rows: list[tuple[str, str, str, str, int]]) -> float:
    """Share of labelled findings that the forest gets right."""
    df: DataFrame = spark.createDataFrame(rows, "body string, before string, second string, whole string, label int")
    df = df.select("label", *[c.alias(n) for n, c in features(*(F.col(c) for c in ("body", "before", "second", "whole"))).items()])
    return df.agg(F.avg(((probability(forest, F.col) >= 0.5).cast("int") == F.col("label")).cast("double"))).first()[0]


if __name__ == "__main__":
    session = SparkSession.builder.master("local[2]").config("spark.ui.enabled", "false").getOrCreate()
    grown = train(session, labelled_findings())
    FILE.write_text(json.dumps(grown, separators=(",", ":")) + "\n")
    print("held-out accuracy", accuracy(session, grown, labelled_findings(4000, SEED + 1)))
