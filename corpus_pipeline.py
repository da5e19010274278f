"""A corpus pipeline of five stages over `documents`; each stage's result is written as Parquet and reread by the next.

Defined cases, for every stage: an empty table gives an empty one; extra columns pass through, whatever their names; texts of
any length are judged whole. Rows are chosen by their doc_id, null being a value like any other, so what holds for a row holds
for all rows of its id. Quality rules reject null and empty texts (and all with fewer than 50 words). Line dedup counts repeated
rows as later copies, which leave no word and go. Of near copies the least doc_id stays (a tie is an id of several rows, of
which equal texts become one), null only where no copy has an id. Mixing takes a row as often as its rate says, the same for
every row of an id. Piece encoding gives a row a row.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmul.llm import op1_mixing, op2_neardup, op5_quality, op7_pieces, op10_lines
from gridmul.llm.common import few_files, fresh, materialise, table

#: Pull of the rates towards 1: the quality rules have left few poor documents, and sound ones shall not make up for them.
PULL = 0.005

#: Not expressible in SQL (divergence from references, hashing forest, fitted rates, piece encoding): tested by brute force.
ORACLE_SQL = None


def _chosen(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """Rows of docs whose doc_id (null is a value) is among ids."""
    name = fresh(docs, "_gm_id")
    few = ids.select(F.col("doc_id").alias(name)).distinct()
    return docs.join(few, docs.doc_id.eqNullSafe(few[name]), "left_semi")


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejected documents go."""
    return few_files(_chosen(docs, op5_quality.quality(docs).where("kept")))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of repeated line runs are deleted; a document of which no word is left goes. n_chars follows the text."""
    removed, lines = fresh(docs, "_gm_removed"), fresh(docs, "_gm_lines")
    found = op10_lines.dedup_lines(docs, lines_col=lines, removed_col=removed)
    kept = found.where((F.col(removed) == 0) | F.col("text").rlike(r"\S"))
    length = F.when(F.col(removed) > 0, F.length("text").cast("long")).otherwise(F.col("n_chars")) if "n_chars" in docs.columns else None
    return few_files(kept.select(*[length.alias("n_chars") if c == "n_chars" else F.col(f"`{c}`") for c in docs.columns]))


def ngram_jaccard_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies stays: the one of the least doc_id."""
    found = materialise(op2_neardup.near_duplicates(docs), "classes", narrow=True)
    least = found.where(F.col("doc_id").eqNullSafe(F.col("class_id"))).groupBy("doc_id").agg(F.count("*").alias("rows"))
    once = _chosen(docs, least.where("rows = 1 OR doc_id IS NULL"))
    # an id of several rows: its copies become one
    return few_files(once.unionByName(_chosen(docs, least.where("rows > 1 AND doc_id IS NOT NULL")).dropDuplicates(["doc_id", "text"])))


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document is taken as often as its fitted rate says; the fraction is settled by a fixed hash of its id."""
    mixed = op1_mixing.mix(docs, op1_mixing.label_domains(table(spark, sf_dir, "labels")), pull=PULL)
    key, rate, times, copy = (fresh(docs, n) for n in ("_gm_id", "_gm_rate", "_gm_copies", "_gm_copy"))
    rates = mixed.groupBy(F.col("doc_id").alias(key)).agg(F.max("rate").alias(rate))
    joined = docs.join(rates, docs.doc_id.eqNullSafe(rates[key]))
    taken = joined.withColumn(times, op1_mixing.copies(F.col(rate), F.col("doc_id"))).where(F.col(times) > 0)
    return few_files(taken.withColumn(copy, F.explode(F.sequence(F.lit(1), F.col(times)))).select(*[F.col(f"`{c}`") for c in docs.columns]))


def sentencepiece(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every whole text."""
    return op7_pieces.encode(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_rules", quality_rules),
    ("line_dedup", line_dedup),
    ("ngram_jaccard_join", ngram_jaccard_join),
    ("source_mixing", source_mixing),
    ("sentencepiece", sentencepiece),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`; the rows of the last one."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
