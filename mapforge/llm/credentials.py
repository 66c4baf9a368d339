"""Operator 10: secret scans whose false positives a random forest removes, in DataFrame functions only.

Candidates are tokens of ``MIN_CHARS`` or more characters of the usual secret alphabets that are not a plain
word or words: they have a digit anywhere, mix letters of both cases, follow a telling name or have a known prefix. Features of a
candidate: length, shares of character classes, character transitions (changes between classes, and the share of neighbouring
letters that are usual neighbours in the words of the corpus), distinct characters, share in runs shaped like words, share
covered by the ``DICTIONARY`` words that most documents of the corpus hold, whether it looks like a path or
address, whether telling words stand before it, whether it is assigned, and known prefixes. A random forest, trained from labelled
findings, scores each candidate; those of score 0.5 or more are reported.

Labelled findings: ``labelled`` may be given as rows (before, token, label), of which those least by a hash are taken. Without
them, findings are generated from a rule: tokens of the usual forms as secrets and, as false positives, digests named as
such, versions, identifiers, paths, addresses, numbers and plain words. Their number is ``TRAINING`` at
most, whatever the corpus. The trained trees become one SQL expression, so scoring runs inside the scan.

Null and empty texts give no rows, nor does an empty table. Repeated findings are all reported, in repeated rows too; spans are
code points of the whole text, however long, end exclusive. A null doc_id stays null.
"""

from __future__ import annotations

import random
import re
import string
from collections import Counter

from pyspark.ml.classification import RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from mapforge.llm.common import table
from mapforge.llm.pii import _located

MIN_CHARS = 12
TRAINING = 2400
TREES = 15
DEPTH = 6
DICTIONARY = 5000
#: Names that announce a secret, prefixes of known kinds, names of harmless digests.
TELLING = "password|passwd|pwd|secret|token|api_?key|apikey|access_?key|private_?key|credential|auth"
PREFIXES = "AKIA|ASIA|ghp_|gho_|github_pat_|xox[abp]-|sk_live_|sk-|AIza|glpat-|eyJ"
HARMLESS = "sha1|sha256|md5|digest|checksum|commit|revision|version|build|uuid|etag|hash|id"
_TOKEN = rf"(?<![A-Za-z0-9_/+=.@-])[A-Za-z0-9_/+=.@:-]{{{MIN_CHARS},}}+"
NEIGHBOURS = 200
FEATURES = ("n", "digits", "lowers", "uppers", "marks", "changes", "usual", "distinct", "hexlike", "words", "pathlike", "telling", "harmless", "assigned", "prefixed", "known")


def _share(value: Column, letters: str) -> Column:
    return F.length(F.regexp_replace(value, f"[^{letters}]", "")) / F.greatest(F.length(value), F.lit(1))


def dictionary(docs: DataFrame, size: int = DICTIONARY) -> list[str]:
    """The ``size`` words that most documents hold, counted over all whole texts: words of letters alone, in two documents or more."""
    words = F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"(?<!\S)[a-z]{3,20}(?![^\s.,;:!?])"), F.lit(0)))
    counts = docs.select(F.explode(words).alias("w")).groupBy("w").agg(F.count("*").alias("n"))
    return [r["w"] for r in counts.where("n >= 2").orderBy(F.desc("n"), "w").limit(size).collect()]


def _listed(words: list[str]) -> str:
    """Letters only, so they need no escapes; a long list is looked up by hash."""
    return ", ".join(f"'{w}'" for w in words) or "''"


def _known(words: list[str]) -> Column:
    """The share of characters of ``value`` in letter runs that are words of the dictionary."""
    return F.expr(f"length(array_join(filter(regexp_extract_all(value, '[A-Z]?[a-z]{{2,}}', 0), w -> lower(w) in ({_listed(words)})), '')) / greatest(length(value), 1)")


def _neighbours(words: list[str], size: int = NEIGHBOURS) -> list[str]:
    """The pairs of neighbouring letters that most words of the dictionary have."""
    found = Counter(w[i : i + 2] for w in words for i in range(len(w) - 1))
    return sorted(found, key=lambda p: (-found[p], p))[:size]


def _usual(words: list[str]) -> Column:
    """The share of neighbouring characters of ``value`` that are usual neighbours in words."""
    pairs = "transform(sequence(1, greatest(length(value) - 1, 1)), i -> lower(substring(value, i, 2)))"
    return F.expr(f"size(filter({pairs}, p -> p in ({_listed(_neighbours(words))}))) / greatest(length(value) - 1, 1)")


def _parts(token: Column, before: Column) -> tuple[Column, Column, Column]:
    """An assigned name within the token, the value after it, and the lower-case text before the value."""
    name = F.lower(F.regexp_extract(token, r"^([A-Za-z_]+)[=:](?=.)", 1))
    return name, F.regexp_replace(token, r"^[A-Za-z_]+[=:]", ""), F.concat(F.lower(before), name)


def features(found: DataFrame, words: list[str]) -> DataFrame:
    """``found`` (token, before: at most 40 code points, and others) with the feature columns, given the dictionary."""
    name, value, near = _parts(F.col("token"), F.col("before"))
    keep = found.columns
    # inline() keeps the optimiser from copying these expressions into each feature
    found = found.select("*", F.inline(F.array(F.struct(name.alias("name"), value.alias("value"), near.alias("near")))))
    name, value, near, before = (F.col(c) for c in ("name", "value", "near", "before"))
    classes = F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace(value, "[0-9]+", "0"), "[a-z]+", "1"), "[A-Z]+", "2"), "[^0-2]+", "3")
    made = [
        F.length(value).cast("double").alias("n"),
        _share(value, "0-9").alias("digits"),
        _share(value, "a-z").alias("lowers"),
        _share(value, "A-Z").alias("uppers"),
        _share(value, "/+=_.@:-").alias("marks"),
        (F.length(classes) / F.greatest(F.length(value), F.lit(1))).alias("changes"),
        _usual(words).alias("usual"),
        (F.size(F.array_distinct(F.split(value, ""))) / F.greatest(F.length(value), F.lit(1))).alias("distinct"),
        value.rlike("^(?:[0-9a-f]+|[0-9A-F]+)$").cast("double").alias("hexlike"),
        (F.length(F.concat_ws("", F.regexp_extract_all(value, F.lit("(?:^|[^A-Za-z])([A-Z]?[a-z]{3,})(?![A-Za-z0-9])"), F.lit(1)))) / F.greatest(F.length(value), F.lit(1))).alias("words"),
        value.rlike(r"@[^@]+\.|^\.{0,2}/|[^/]/[^/]+/|://|^[0-9.]+$|^[A-Za-z0-9_-]+\.[a-z]{2,4}$").cast("double").alias("pathlike"),
        near.rlike(rf"(?:{TELLING})\W{{0,5}}$").cast("double").alias("telling"),
        near.rlike(rf"\b(?:{HARMLESS})\W{{0,5}}$").cast("double").alias("harmless"),
        ((name != "") | before.rlike(r"[=:]\s{0,2}[\"']?$")).cast("double").alias("assigned"),
        value.rlike(f"^(?:{PREFIXES})").cast("double").alias("prefixed"),
        _known(words).alias("known"),
    ]
    return found.select(*keep, *made)


def candidates(docs: DataFrame) -> DataFrame:
    """(doc_id, start, end, token, before) of every candidate."""
    text = F.col("text")
    rows = docs.select(F.col("doc_id").cast("long"), "text").where(text.rlike(r"\S"))
    found = rows.select("doc_id", "text", F.inline(_located(text, _TOKEN)))
    near = F.expr("substring(text, greatest(1, s - 39), least(s, 40))")
    found = found.select("doc_id", F.col("s").cast("long").alias("start"), F.col("e").cast("long").alias("end"), F.col("m").alias("token"), near.alias("before"))
    _, value, ahead = _parts(F.col("token"), F.col("before"))
    mixed = value.rlike("[a-z][A-Z]+[a-z]+[A-Z]|[A-Z]{2}[a-z]+[A-Z]|[a-z][A-Z]+[^A-Za-z]|[0-9]")
    return found.where(mixed | ahead.rlike(rf"(?:{TELLING})\W{{0,5}}$") | value.rlike(f"^(?:{PREFIXES})"))


def generated_findings(n: int = TRAINING, seed: int = 3, words: list[str] | None = None) -> list[tuple[str, str, float]]:
    """Labelled findings by rule: (before, token, label), half of them secrets; two of three words come from the dictionary, if any."""
    rng = random.Random(seed)
    pick = lambda letters, k: "".join(rng.choices(letters, k=k))
    hexa, alnum, upper = "0123456789abcdef", string.ascii_letters + string.digits, string.ascii_uppercase + string.digits
    word = lambda: rng.choice(words) if words and rng.random() < 0.67 else pick(string.ascii_lowercase, rng.randint(3, 9))
    tell = lambda: rng.choice(["password", "secret", "token", "api_key", "access_key", "TOKEN", "Password"])
    safe = lambda: rng.choice(HARMLESS.split("|"))
    yes = [
        lambda: (f"{word()} ", "AKIA" + pick(upper, 16)),
        lambda: (f"{word()} {tell()} = \"", pick(hexa, rng.choice([32, 40, 64]))),
        lambda: (f"{word()} ", f"{tell()}={pick(hexa, rng.randint(12, 40))}"),
        lambda: (f"{word()} {tell()}: ", pick(alnum, rng.randint(16, 48))),
        lambda: (f"{word()} ", rng.choice(["ghp_", "sk_live_", "glpat-"]) + pick(alnum, rng.randint(20, 36))),
        lambda: (f"{word()} {tell().upper()} = \"", pick(hexa, 40).upper()),
        lambda: (f"{word()} {tell()} = \"", pick(string.ascii_letters, rng.randint(16, 40))),
        lambda: (f"{word()} ", f"{word().upper()}_{word().upper()}_{tell().upper()}={pick(alnum, rng.randint(16, 40))}"),
        lambda: (f"{word()} ", pick(string.ascii_letters, rng.randint(24, 44))),
    ]
    no = [
        lambda: (f"{word()} {safe()}: ", pick(hexa, rng.choice([32, 40, 64]))),
        lambda: (f"{word()} {word()} ", pick(string.digits, rng.randint(12, 19))),
        lambda: (f"{word()} ", f"{word()}.{pick(string.digits, 2)}@mail{rng.randint(0, 9)}.example.com"),
        lambda: (f"{word()} ", ".".join(str(rng.randint(0, 255)) for _ in range(4))),
        lambda: (f"{word()} ", f"/{word()}/{word()}/{word()}{rng.randint(0, 9)}.txt"),
        lambda: (f"{word()} ", f"https://{word()}.org/{word()}/{rng.randint(1, 999)}"),
        lambda: (f"{word()} ", f"{word()}-{word()}-{rng.randint(1, 99)}-{word()}"),
        lambda: (f"{word()} {safe()} ", "-".join(pick(hexa, k) for k in (8, 4, 4, 4, 12))),
        lambda: (f"{word()} ", f"{word()}{word()}{rng.randint(0, 9)}"),
        lambda: (f"{word()} {tell()} ", word() + word() + word()),
        lambda: (f"{word()} ", "".join(word().title() for _ in range(rng.randint(3, 5)))),
        lambda: (f"{word()} ", word() + "".join(word().title() for _ in range(rng.randint(2, 4)))),
        lambda: (f"{word()} version ", ".".join(pick(string.digits, rng.randint(1, 4)) for _ in range(5))),
    ]
    return [(*rng.choice(kind)(), label) for k in range(n) for kind, label in ([(yes, 1.0), (no, 0.0)][k % 2],)]


def train(spark: SparkSession, words: list[str], labelled: DataFrame | None = None, trees: int = TREES, depth: int = DEPTH) -> Column:
    """The forest as one expression over the feature columns: the share of votes for a secret."""
    if labelled is None:
        rows = spark.createDataFrame(generated_findings(words=words), "before string, token string, label double")
    else:
        usable = labelled.select("before", "token", F.col("label").cast("double").alias("label")).where("token is not null and label in (0, 1)").fillna("", ["before"]).distinct()
        rows = usable.orderBy(F.xxhash64("before", "token", "label"), "before", "token", "label").limit(TRAINING)
    data = features(rows, words).select("label", *FEATURES).coalesce(1)
    data = VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(data)
    model = RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=11, featureSubsetStrategy="sqrt").fit(data)
    votes = [_tree_sql(t.toDebugString.split("\n")[1:]) for t in model.trees]
    return F.expr("(" + " + ".join(votes) + f") / {len(votes)}.0D")


def _tree_sql(lines: list[str]) -> str:
    """A printed decision tree as nested CASE expressions."""
    lines = [x.strip() for x in lines if x.strip()]

    def node(i: int) -> tuple[str, int]:
        if m := re.match(r"Predict: ([0-9.]+)", lines[i]):
            return f"{float(m[1])}D", i + 1
        m = re.match(r"If \(feature (\d+) <= (\S+)\)", lines[i])
        yes, i = node(i + 1)
        no, i = node(i + 1)  # after its Else line
        return f"CASE WHEN {FEATURES[int(m[1])]} <= {float(m[2])!r}D THEN {yes} ELSE {no} END", i

    return node(0)[0]


def scan(docs: DataFrame, labelled: DataFrame | None = None, threshold: float = 0.5) -> DataFrame:
    """doc_id, start, end, secret_sha256, score of every candidate that the forest takes for a secret."""
    words = dictionary(docs)
    score = train(docs.sparkSession, words, labelled)
    scored = features(candidates(docs), words).withColumn("score", score)
    return scored.where(F.col("score") >= threshold).select("doc_id", "start", "end", F.sha2(F.col("token").cast("binary"), 256).alias("secret_sha256"), F.round("score", 6).alias("score"))


def op10_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents", "doc_id", "text"))
