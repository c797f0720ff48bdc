"""Corpus pipeline over ``documents``: quality, exact copies, near copies, personal data, packing.

Each stage takes (spark, docs, sf_dir) and works on all rows that its predecessor kept. All
but the last return the columns of ``documents``; the last returns the packed pieces. An
empty table passes through every stage as one; columns beside doc_id, text and n_chars are
carried along and not read. Null and blank texts are empty texts, which equal each other,
have no near copies and become a piece with the end id alone. Null ids are ids after all
others; rows of one id are rows of their own.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from veilstat.llm.common import read_table, sized, stage
from veilstat.llm.exact_dedup import exact_groups, normalised
from veilstat.llm.ngram_join import ngram_rows, text_key
from veilstat.llm.packing import pack_documents
from veilstat.llm.pii import mask_pii
from veilstat.llm.quality import fit_model, keep_quality

#: Near copies: shingles of five words, similarity of 0.8 or more.
NEAR_WORDS, NEAR_PERCENT = 5, 80


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier does not reject (score of at least 0.3); equal rows stay or go together."""
    return keep_quality(docs, fit_model(docs, read_table(spark, sf_dir, "labels")))


def keep_rows(docs: DataFrame, mark: Column, told: DataFrame) -> DataFrame:
    """Rows of ``docs`` that ``told`` (doc_id, mark, stays, copies) keeps, one of those that share id and mark.

    ``mark`` is the text fingerprint of a row. ``told`` has one row for each id and mark that
    goes or that several rows share; null ids match each other. Of rows that share both, the
    least by all columns stays.
    """
    told = stage(told.where("NOT stays OR copies > 1").select(F.col("doc_id").alias("told_id"), F.col("mark").alias("told_mark"), "stays"), "told")
    marked = docs.select(F.struct("*").alias("row"), F.col("doc_id").alias("id"), mark.alias("mark"))  # no name of docs can clash
    same = F.col("id").eqNullSafe(F.col("told_id")) & (F.col("mark") == F.col("told_mark"))
    out = marked.join(sized(told, None), same, "left_anti").select("row")
    repeats = told.where("stays")
    if not repeats.isEmpty():
        out = out.unionByName(marked.join(sized(repeats, None), same).groupBy("told_id", "told_mark").agg(F.min("row").alias("row")).select("row"))
    return out.select("row.*")


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row, the first of the smallest id (nulls last), of each group of equal texts; of fully equal rows one."""
    groups = exact_groups(docs)
    told = groups.groupBy("doc_id", F.col("text_sha256").alias("mark")).agg(F.bool_and("kept").alias("stays"), F.count("*").alias("copies"))
    return keep_rows(docs, F.sha2(normalised(F.col("text")), 256), told)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row, the first of the smallest id (nulls last), of each group linked by near copies.

    Blank texts link with nothing and stay.
    """
    rows = ngram_rows(docs, NEAR_WORDS, NEAR_PERCENT).where("n > 0").groupBy("label", "doc_id", "key").agg(F.count("*").alias("copies"))
    rows = stage(rows.withColumn("place", F.struct(F.isnull("doc_id").alias("late"), "doc_id", "key")), "near-rows")
    first = rows.groupBy("label").agg(F.min("place").alias("first"))
    told = rows.join(first, "label").select("doc_id", F.col("key").alias("mark"), F.col("place").eqNullSafe(F.col("first")).alias("stays"), "copies")
    return keep_rows(docs, text_key(F.col("text")), told)


def pii_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data masked in the texts; n_chars follows the new text; null texts stay null, repeated rows stay."""
    masked = mask_pii(docs)
    return masked.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else masked


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents with their sequence and offset, those of every row that repeats."""
    import public_tokenizers

    return pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [
    ("quality", quality_stage),
    ("exact_dedup", exact_stage),
    ("near_dedup", near_stage),
    ("pii", pii_stage),
    ("packing", packing_stage),
]

#: A learned classifier and token ids are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, step in STAGES[:-1]:
        docs = stage(step(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
