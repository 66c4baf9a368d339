"""Corpus pipeline: toxicity, line dedup, near-duplicate removal, PII redaction, packing.

Each stage takes (spark, docs, sf_dir) and works on all rows that its predecessor kept; its decisions
take effect on what it returns. All but the last return the columns of ``documents`` and keep any
others that came in, whatever their names: they are numbered while an operator adds columns of its own.
Null and empty texts stay until packing, where each is one piece; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from mapforge.llm import lines, neardup, packing, pii, toxicity
from mapforge.llm.common import persist_table, table


def _renamed(docs: DataFrame) -> DataFrame:
    """``docs`` with doc_id and text as they are and all other columns numbered, so that no name an operator adds meets one of them."""
    return docs.toDF(*[c if c in ("doc_id", "text") else f"c{k}" for k, c in enumerate(docs.columns)])


def _restored(found: DataFrame, docs: DataFrame, changed: Column, text: Column) -> DataFrame:
    """The columns of ``docs`` again, where ``changed`` with another text and its number of code points."""

    def column(k: int, name: str, kind: str) -> Column:
        if name == "text":
            return F.when(changed, text).otherwise(F.col("text"))
        old = F.col(name if name == "doc_id" else f"c{k}")
        return F.when(changed, F.length(text).cast(kind)).otherwise(old) if name == "n_chars" else old

    return found.select(*[column(k, name, kind).alias(name) for k, (name, kind) in enumerate(docs.dtypes)])


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored 0.5 or more are dropped; null and empty texts stay."""
    model = toxicity.fit(docs.select("doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "toxic"))
    kept = toxicity.score(_renamed(docs), model).where("score < 0.5").drop("score")
    return kept.toDF(*docs.columns)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated lines leave their documents; a document all of whose lines are repeated goes. Null and blank texts stay."""
    done = lines.dedup(_renamed(docs))
    emptied = (F.col("removed") > 0) & ~F.col("text").rlike(r"\S")
    return _restored(done.where(~F.coalesce(emptied, F.lit(False))), docs, F.col("removed") > 0, F.col("text"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each class stays: the one of least doc_id, and of rows with that id and text the least one.

    Rows are told apart by doc_id and text, so a doc_id that two texts share loses only the text that is a copy. Null
    ids count as the largest. Texts without any word are in no class: they all stay.
    """
    found = neardup.members(docs.select("doc_id", "text"))
    same = (F.col("doc_id").eqNullSafe(F.col("first.doc_id"))) & (F.col("mark") == F.col("first.mark"))
    gone = found.where(~same).select("doc_id", "mark")
    twice = found.where(same & (F.col("n_links") > 0)).groupBy("doc_id", "mark").agg(F.count("*").alias("n")).where("n > 1").select("doc_id", "mark")
    # gone: other rows of a class; twice: rows that repeat both id and text of a class's first row
    marks = persist_table(gone.withColumn("twice", F.lit(False)).union(twice.withColumn("twice", F.lit(True))).distinct(), "copies")
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), "doc_id", F.xxhash64("text").alias("mark"))
    other = marks.select(F.col("doc_id").alias("m_id"), F.col("mark").alias("m_mark"), "twice")
    met = rows.join(other, (F.col("mark") == F.col("m_mark")) & F.col("doc_id").eqNullSafe(F.col("m_id")), "left")
    once = met.where("twice is null").select("row.*")
    sortable = [F.col(f"row.`{c}`") for c, kind in docs.dtypes if "map<" not in kind and "variant" not in kind]
    first = met.where("twice").groupBy("m_id", "m_mark").agg(F.min_by("row", F.struct(*sortable)).alias("row")).select("row.*")
    return once.union(first)


def redact_pii(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every identifier is replaced by its kind in brackets."""
    marked = pii.attach(_renamed(docs), pii.added(docs.select("doc_id", "text")))
    return _restored(marked, docs, F.size("spans") > 0, pii.redact(F.col("text"), F.col("spans")))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents that are left, with their places in the sequences."""
    return packing.pack(docs.select("doc_id", "text"))


STAGES = [
    ("toxicity", drop_toxic),
    ("line dedup", drop_repeated_lines),
    ("n-gram jaccard join", drop_near_duplicates),
    ("pii", redact_pii),
    ("packing", pack),
]

#: SQL expresses neither trained scores nor this packing; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = persist_table(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}")
    return STAGES[-1][1](spark, docs, sf_dir)
