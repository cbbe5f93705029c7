"""The corpus pipeline: quality, line dedup, near duplicates, mixing, packing.

STAGES lists (name, function); a function takes (spark, docs, sf_dir) and
returns a DataFrame, which is written as Parquet and read again as the next
one's docs. All but the last return the columns of documents, further columns
that docs has included, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treefold.llm.common import documents, fresh, labels, materialise, text_or_empty
from treefold.llm.line_dedup import dedup_lines
from treefold.llm.mixing import mixed_documents
from treefold.llm.near_dups import near_groups
from treefold.llm.packing import pack
from treefold.llm.quality import with_quality


def _sized(docs: DataFrame) -> DataFrame:
    return docs.withColumn("n_chars", F.char_length("text").cast("long"))


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects (score below one half) go.

    It learns from the labelled rows of docs. A null text is scored as the empty
    one; rows that repeat an id are scored each, null ids too. Without labelled
    rows of both classes every score is one half, and all stay.
    """
    score = fresh(docs, "__quality_score")
    scored = with_quality(docs, labels(spark, sf_dir), score_col=score)
    return scored.where(F.col(score) >= 0.5).select(*docs.columns)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A line that several documents hold stays in the first of them.

    Keys of ten code points or more count. A null text becomes the empty one, as
    does one that loses all its lines; the row stays. Null ids count as one
    document after all others, rows that repeat an id as one document.
    """
    names = tuple(fresh(docs, name) for name in ("kept_text", "n_lines", "n_dropped"))
    deduped = dedup_lines(docs, names=names).withColumn("text", F.col(names[0]))
    return _sized(deduped).select(*docs.columns)


def ngram_jaccard_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near duplicates stays: the one with the least id (then text hash, then other columns).

    Rows are told apart by id and text, as an id may be repeated with other texts.
    Rows without an id, and texts without words, are in no group and stay. Line
    dedup has gone before: near copies have lost the lines that they share, so most
    are no longer alike here, and those that still are go.
    """
    groups = materialise(near_groups(docs).where("NOT stays OR copies").select("doc_id", "text_key", "stays"), "near-groups")
    key = fresh(docs, "__text_key")
    keyed = docs.withColumn(key, F.xxhash64(text_or_empty("text")))
    dropped = groups.where("NOT stays").select("doc_id", F.col("text_key").alias(key)).distinct()
    left = keyed.join(dropped, ["doc_id", key], "left_anti")
    # what stays may itself be repeated, row for row
    repeated = groups.where("stays").groupBy("doc_id", F.col("text_key").alias(key)).count().where("count > 1").select("doc_id", key)
    if not repeated.limit(1).count():
        return left.select(*docs.columns)
    others = [c for c in docs.columns if c != "doc_id"]
    single = left.join(repeated, ["doc_id", key], "left_semi").groupBy("doc_id", key).agg(F.min(F.struct(*others)).alias("row"))
    return left.join(repeated, ["doc_id", key], "left_anti").select(*docs.columns).unionByName(single.select("doc_id", "row.*"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources are drawn to their target weights; a document that is read twice has two rows, one cut between shards a row for each part.

    A document without words is not drawn. Null and repeated ids and null sources
    take part as rows of their own.
    """
    return _sized(mixed_documents(docs)).select(*docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces and their places in sequences of 2048, for every row of docs; an empty or null text is its end id alone."""
    return pack(docs)


STAGES = [
    ("quality_classifier", quality_classifier),
    ("line_dedup", line_dedup),
    ("ngram_jaccard_join", ngram_jaccard_join),
    ("mixing", mixing),
    ("packing", packing),
]

#: The classifier and the packing have no SQL; tests/llm/test_pipeline.py compares every stage with a plain Python version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
