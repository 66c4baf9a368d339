"""Operator 2: personal data by bootstrapped contextual extraction, in DataFrame functions only.

Base entities (e-mail, IPv4, card and phone numbers by fixed patterns) are the seeds. Every other token that has a digit
or an at sign is an instance, and so are digit groups joined by single spaces; what a base entity covers is none. A lexical pattern is the
context of an entity: the two words left of it, the one word left of it, or the word left and the word right of it
(lower case, digits as 0, the nearest ``REACH`` code points). Patterns and instances form a graph whose scores are computed in turn:

* a pattern's score for a kind is the belief its instances have for that kind, summed, over their number plus one; it counts
  where at least ``MIN_SUPPORT`` distinct ones are believed;
* a shape (runs of digits and letters, marks as they are) has the same score over all instances of that shape;
* an unseen instance is believed as its best pattern says, raised by its shape. It is accepted at ``CONFIDENT`` where its form is
  one that the kind can have, at ``CERTAIN`` where it is any other form with four digits or more.

Rounds go on until no instance is accepted or dropped any more, ``MAX_ROUNDS`` at most. Accepted instances are added as
spans at each of their places in the contexts that brought them in; base spans always stay.

Position lists are computed by cutting texts with the same pattern that extracts the entities, so
start and end are code points of the whole text. The patterns are written so that Java's matcher
neither recurses nor starts over inside one run of letters, however long: see the notes at each.
Null text counts as empty and has no spans. Rows that repeat an id and text have the same spans; ids may be null; an empty
table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from mapforge.llm.common import persist_table, table

KINDS = ("email", "ip", "card", "phone")
MAX_ROUNDS = 12
MIN_SUPPORT = 5
CONFIDENT = 0.5
CERTAIN = 0.8
REACH = 160

#: What counts as an entity of each kind, rewritten without loss for linear matching.
#: email and ip: a match can only start where its run of letters starts or where the last match ended.
#: card: single separators between digits are first turned into one mark, so that one class of
#: characters stands for the repeated group.
_PATTERNS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++\.[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)*+",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9][0-9\x01]+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: An instance: digit groups joined by single spaces, or a word with a digit or an at sign.
_TOKEN = r"(?<!\S)(?:[(+]?[0-9][0-9().:/-]*+(?:\x20[(]?[0-9][0-9().:/-]*+)++(?!\S)|[^\s0-9@]*+[0-9@]\S*+)"
_MATCHES = "array<struct<m:string,s:int,e:int>>"
SPANS = "array<struct<k:int,s:int,e:int>>"


def _let(value: Column, use) -> Column:
    """``use(value)`` with the value computed once, also where ``use`` needs it inside a lambda."""
    return F.transform(F.array(value), lambda v: use(v))[0]


def _located(text: Column, pattern: str, block: int = 128) -> Column:
    """Matches of ``pattern`` with start and end, as an array: the gaps between matches give the places.

    Places are summed up in blocks and the blocks then shifted, so that many matches cost little
    more than their number.
    """
    kind = f"struct<at:int,out:{_MATCHES}>"
    start = F.struct(F.lit(0).alias("at"), F.array().cast(_MATCHES).alias("out")).cast(kind)

    def step(acc: Column, x: Column) -> Column:
        first = acc["at"] + x["g"]
        end = first + F.length(x["m"])
        hit = F.struct(x["m"].alias("m"), first.alias("s"), end.alias("e"))
        return F.struct(end.alias("at"), F.concat(acc["out"], F.array(hit)).alias("out"))

    def shifted(acc: Column, x: Column) -> Column:
        moved = F.transform(x["out"], lambda h: F.struct(h["m"].alias("m"), (h["s"] + acc["at"]).alias("s"), (h["e"] + acc["at"]).alias("e")))
        return F.struct((acc["at"] + x["at"]).alias("at"), F.concat(acc["out"], moved).alias("out"))

    def placed(steps: Column) -> Column:
        blocks = F.sequence(F.lit(0), F.floor((F.size(steps) - 1) / block).cast("int"))
        parts = F.transform(blocks, lambda i: F.aggregate(F.slice(steps, i * block + 1, F.lit(block)), start, step))
        return F.when(F.size(steps) > 0, F.aggregate(parts, start, shifted, lambda acc: acc["out"])).otherwise(F.array().cast(_MATCHES))

    def cut(found: Column) -> Column:
        gaps = F.slice(F.split(text, pattern, -1), F.lit(1), F.size(found))
        return _let(F.zip_with(gaps, found, lambda g, m: F.struct(F.length(g).alias("g"), m.alias("m"))), placed)

    return _let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda found: F.when(F.size(found) > 0, cut(found)).otherwise(F.array().cast(_MATCHES)))


def _if(condition: Column, value: Column) -> Column:
    return F.when(condition, value).otherwise(F.array().cast(_MATCHES))


def base_matches(text: Column) -> dict[str, Column]:
    """Base entities of a non-null text by kind: arrays of (m, s, e)."""
    digits = lambda m: F.regexp_replace(m, "[^0-9]", "")
    octet = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
    marked = F.regexp_replace(F.translate(text, "\x01", "\x02"), "(?<=[0-9])[ -](?=[0-9])", "\x01")
    email = _if(F.contains(text, F.lit("@")), _located(text, _PATTERNS["email"]))
    ip = _if(text.rlike(r"[0-9]\.[0-9]+\."), _located(text, _PATTERNS["ip"]))
    card = _if(text.rlike("[0-9][0-9 -]{14,}"), _located(marked, _PATTERNS["card"]))
    phone = _if(F.contains(text, F.lit("+")), _located(text, _PATTERNS["phone"]))
    return {
        "email": email,
        "ip": F.filter(ip, lambda x: x["m"].rlike(rf"^{octet}(?:\.{octet}){{3}}$")),
        "card": F.filter(card, lambda x: F.length(digits(x["m"])).between(16, 19) & F.call_function("luhn_check", digits(x["m"]))),
        "phone": F.filter(phone, lambda x: F.length(digits(x["m"])).between(8, 15)),
    }


def _plain(word: Column) -> Column:
    return F.regexp_replace(F.lower(word), "[0-9]", "0")


def _contexts(text: Column, start: Column, end: Column) -> Column:
    """The patterns at a place: kind of context and its words; ``^`` and ``$`` stand for none."""
    near = F.substring(text, F.greatest(F.lit(1), start - (REACH - 1)), F.least(start, F.lit(REACH)))
    after = F.substring(text, end + 1, F.lit(REACH))
    words = F.filter(F.split(_plain(near), r"\s+"), lambda w: w != "")
    one = F.coalesce(F.get(words, F.size(words) - 1), F.lit("^"))
    two = F.coalesce(F.get(words, F.size(words) - 2), F.lit("^"))
    right = F.coalesce(F.get(F.filter(F.split(_plain(after), r"\s+"), lambda w: w != ""), F.lit(0)), F.lit("$"))
    return _let(F.struct(one.alias("one"), two.alias("two"), right.alias("right")), lambda c: F.array(F.concat_ws(" ", F.lit("2"), c["two"], c["one"]), F.concat_ws(" ", F.lit("1"), c["one"]), F.concat_ws(" ", F.lit("b"), c["one"], c["right"])))


def shape(token: Column) -> Column:
    """Runs of digits as 0 with their length up to three and over, runs of letters as a, marks as they are."""
    digits = F.regexp_replace(F.regexp_replace(token, r"[0-9]{4,}", "\x010"), r"[0-9]{1,3}", "0")
    return F.regexp_replace(digits, r"[\p{L}]+", "a")


def _fits(token: Column, kind: Column) -> Column:
    """Whether a token has a form that the kind can have."""
    digits = F.length(F.regexp_replace(token, "[^0-9]", ""))
    return (
        F.when(kind == 0, token.rlike(r"^\S+@\S+$"))
        .when(kind == 1, token.rlike(r"^[0-9]{1,3}(?:[.:][0-9]{1,3}){3}$"))
        .when(kind == 2, token.rlike(r"^[0-9][0-9 -]+$") & digits.between(12, 19))
        .otherwise(token.rlike(r"^[+(]?[0-9][0-9 ().:/-]*[0-9]$") & digits.between(6, 15))
    )


def scan(docs: DataFrame) -> DataFrame:
    """(doc_id, mark, instances) of documents with any digit or at sign, once for each doc_id and text.

    ``mark`` is a hash of the text, so that rows repeating a doc_id with another text stay apart.
    """
    rows = docs.select("doc_id", F.xxhash64("text").alias("mark"), "text").where(F.col("text").rlike("[0-9@]"))
    text = F.col("text")
    # inline() keeps the optimiser from copying these expressions to every later use
    found = F.struct(*[x.alias(k) for k, x in base_matches(text).items()], _located(text, _TOKEN).alias("loose"))
    rows = rows.select("doc_id", "mark", "text", F.inline(F.array(found)))

    def named(n: int, found: Column | str) -> Column:
        return F.transform(found, lambda x: F.struct(F.lit(n).alias("k"), x["m"].alias("m"), x["s"].alias("s"), x["e"].alias("e"), _contexts(text, x["s"], x["e"]).alias("contexts")))

    rows = rows.withColumn("base", _tagged({k: F.col(k) for k in KINDS}))
    lead = lambda x: F.length(F.regexp_extract(x["m"], r"^[^A-Za-z0-9+(]*+", 0))
    bare = lambda x: F.regexp_replace(F.regexp_replace(x["m"], r"^[^A-Za-z0-9+(]++", ""), r"(?<=[A-Za-z0-9])[^A-Za-z0-9]++$", "")
    loose = F.transform("loose", lambda x: F.struct(bare(x).alias("m"), (x["s"] + lead(x)).alias("s"), (x["s"] + lead(x) + F.length(bare(x))).alias("e")))
    free = _let(F.col("base"), lambda base: F.filter(loose, lambda x: (x["m"] != "") & ~F.exists(base, lambda b: (b["s"] < x["e"]) & (x["s"] < b["e"]))))
    instances = F.concat(*[named(n, k) for n, k in enumerate(KINDS)], named(-1, free))
    found = rows.select("doc_id", "mark", instances.alias("instances")).where(F.size("instances") > 0)
    return found.groupBy("doc_id", "mark").agg(F.first("instances").alias("instances"))


def bootstrap(instances: DataFrame, max_rounds: int = MAX_ROUNDS, min_support: int = MIN_SUPPORT, confident: float = CONFIDENT, certain: float = CERTAIN) -> DataFrame:
    """``(context, m, k)`` of unseen instances that are accepted, from rows (k, m, context); k is -1 for unseen."""
    edges = persist_table(instances.groupBy("context", "m").agg(F.max("k").alias("k")), "pii-graph")
    # Patterns without a believed seed at first can only gain from others' finds, so all contexts stay in the graph.
    size = persist_table(edges.groupBy("context").agg(F.count("*").alias("n")).where(F.col("n") >= min_support), "pii-sizes")
    nodes = persist_table(edges.groupBy("m").agg(F.max("k").alias("k")).withColumn("shape", shape(F.col("m"))), "pii-nodes")
    shapes = persist_table(nodes.groupBy("shape").agg(F.count("*").alias("n")).where(F.col("n") >= min_support), "pii-shapes")
    seeds = nodes.where("k >= 0").select("m", "k", F.lit(1.0).alias("belief"))
    unseen = nodes.where("k < 0").select("m", "shape")
    open_ = edges.join(unseen.select("m"), "m", "left_semi").select("context", "m")
    belief, mark = seeds, None
    found = None
    for _ in range(max_rounds):
        held = edges.select("context", "m").join(belief, "m").groupBy("context", "k").agg(F.sum("belief").alias("held")).where(F.col("held") >= min_support)
        patterns = persist_table(held.join(size, "context").select("context", "k", (F.col("held") / (F.col("n") + 1)).alias("score")).where(F.col("score") >= confident / 2), "pii-patterns")
        by_shape = nodes.select("m", "shape").join(belief, "m").groupBy("shape", "k").agg(F.sum("belief").alias("held"))
        by_shape = by_shape.join(shapes, "shape").select("shape", "k", (F.col("held") / (F.col("n") + 1)).alias("typical"))
        drawn = open_.join(patterns, "context").groupBy("m", "k").agg(F.max("score").alias("score"))
        scored = drawn.join(unseen, "m").join(by_shape, ["shape", "k"], "left")
        scored = scored.withColumn("belief", F.col("score") + (1 - F.col("score")) * 0.5 * F.coalesce("typical", F.lit(0.0)))
        many = F.length(F.regexp_replace("m", "[^0-9]", "")) >= 4
        good = (F.col("belief") >= confident) & _fits(F.col("m"), F.col("k")) | (F.col("belief") >= certain) & many
        best = scored.where(good).groupBy("m").agg(F.max(F.struct("belief", "k")).alias("b"))
        found = persist_table(best.select("m", "b.k", "b.belief"), "pii-belief")
        belief = seeds.union(found)
        new = tuple(found.agg(F.count("*"), F.sum(F.xxhash64("m", "k").cast("decimal(38,0)"))).first())
        if new == mark or not new[0]:
            break
        mark = new
    return open_.join(found.select("m", "k"), "m").join(patterns.select("context", "k"), ["context", "k"], "left_semi").select("context", "m", "k")


def _tagged(found: dict[str, Column]) -> Column:
    """Kind, start and end of base matches."""

    def of_kind(n: int) -> Column:
        return F.transform(found[KINDS[n]], lambda x: F.struct(F.lit(n).alias("k"), x["s"].alias("s"), x["e"].alias("e")))

    return F.concat(*map(of_kind, range(len(KINDS))))


def added(docs: DataFrame) -> DataFrame:
    """(doc_id, mark, added): spans that bootstrapping adds, for each (doc_id, hash of text) that has any."""
    each = scan(docs.select("doc_id", "text")).select("doc_id", "mark", F.explode("instances").alias("i")).select("doc_id", "mark", "i.*")
    each = persist_table(each, "pii-instances").withColumn("context", F.explode("contexts"))
    accepted = persist_table(bootstrap(each.select("k", "m", "context")), "pii-found")
    met = each.where("k < 0").drop("k").join(accepted, ["context", "m"])
    return persist_table(met.groupBy("doc_id", "mark").agg(F.collect_set(F.struct("k", "s", "e")).alias("added")), "pii-added")


def attach(docs: DataFrame, found: DataFrame) -> DataFrame:
    """``docs`` with ``base`` and ``spans``, both empty where a text has none; ``found`` as :func:`added` makes it.

    Base spans are found in place, so texts meet only the few rows that have added ones.
    """
    text = F.coalesce("text", F.lit(""))
    keep = [F.col(f"d.`{c}`") for c in docs.columns if c not in ("base", "spans")]
    # inline() keeps the optimiser from copying the base expressions to every later use
    base = F.when(text.rlike("[0-9@]"), F.sort_array(_tagged(base_matches(text)))).otherwise(F.array().cast(SPANS))
    rows = docs.alias("d").select(*keep, F.xxhash64("text").alias("__mark"), F.inline(F.array(F.struct(base.alias("__base")))))
    right = found.select(F.col("doc_id").alias("__id"), F.col("mark").alias("__m"), "added")
    joined = rows.alias("d").join(right, (F.col("__mark") == F.col("__m")) & F.col("d.doc_id").eqNullSafe(F.col("__id")), "left")
    spans = F.when(F.col("added").isNull(), F.col("__base")).otherwise(F.sort_array(F.concat("__base", "added")))
    return joined.select(*keep, F.col("__base").alias("base"), spans.alias("spans"))


def extract(docs: DataFrame) -> DataFrame:
    """``docs`` (doc_id, text and others) with ``base`` and ``spans`` (base ones and added ones, by kind and start)."""
    return attach(docs, added(docs))


def redact(text: Column, spans: Column) -> Column:
    """The text with every span replaced by its kind in brackets; overlapping spans fall together, the first names them."""
    ordered = F.array_sort(F.transform(spans, lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["k"].alias("k"))))
    names = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])

    def step(acc: Column, x: Column) -> Column:
        gap = F.substring(text, acc["at"] + 1, F.greatest(x["s"] - acc["at"], F.lit(0)))
        said = F.when(x["s"] >= acc["at"], F.concat(acc["out"], gap, F.element_at(names, x["k"] + 1))).otherwise(acc["out"])
        return F.struct(F.greatest(acc["at"], x["e"]).alias("at"), said.alias("out"))

    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    done = F.aggregate(ordered, start, step, lambda acc: F.concat(acc["out"], F.substring(text, acc["at"] + 1, F.length(text))))
    return F.when(F.size(spans) > 0, done).otherwise(text)


def _written(spans: Column) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.element_at(names, x["k"] + 1), x["s"], x["e"])), ",")


def op2_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    full = extract(table(spark, sf_dir, "documents", "doc_id", "text")).drop("text")

    def count(n: int) -> Column:
        return F.size(F.filter("base", lambda x: x["k"] == n)).cast("long").alias(f"n_{KINDS[n]}")

    return full.select("doc_id", *map(count, range(len(KINDS))), F.sha2(_written(F.col("base")).cast("binary"), 256).alias("base_sha256"), _written(F.col("spans")).alias("spans"), F.size("spans").cast("long").alias("n_spans"))
