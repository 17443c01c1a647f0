"""The corpus pipeline: documents -> language ID -> line dedup -> SimHash near-dedup -> decontamination -> packing.

Each stage takes (spark, docs, sf_dir), works on all rows that the one before it
kept, and returns the columns of ``documents``; the last returns packed pieces.
Other columns of ``docs`` are ignored, and an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from quadpost.llm import decontamination, language, lines, packing, simhash
from quadpost.llm.staging import written

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: Stages after line dedup hold too much that SQL cannot express.
ORACLE_SQL = None


def _documents(df: DataFrame) -> DataFrame:
    return df.select(*COLUMNS)


def _row() -> Column:
    """A document is its doc_id and its text: rows that share only one of them are judged apart."""
    return F.xxhash64(F.col("doc_id").cast("long"), F.col("text").cast("string"))


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the model rejects go; null texts and texts without a letter are rejected, repeated rows fare alike."""
    return _documents(language.keep_accepted(docs, language.fit(docs)))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of repeated line runs go; a document that loses all its lines goes with them. n_chars follows the text.

    Null texts stay as they are; rows with equal doc_id and text are one document.
    """
    kept = lines.dedup_lines(docs).where((F.col("n_removed") == 0) | F.col("text").rlike(r"\S"))
    return _documents(kept.withColumn("n_chars", F.when(F.col("n_removed") > 0, F.char_length("text").cast("long")).otherwise(F.col("n_chars"))))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near-duplicates (five-word shingles, similarity 0.8) the document with the smallest doc_id stays, once.

    A null doc_id comes after all others; texts without words are one class.
    """
    found = simhash.wide_classes(docs).where("keep").select(F.col("row").alias("_keep")).distinct()
    return _documents(docs.withColumn("_row", _row()).join(found, F.col("_row") == F.col("_keep"), "left_semi").dropDuplicates(["_row"]))


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the contamination rule holds against the benchmark go; null and empty texts stay."""
    keyed = docs.select(_row().alias("doc_id"), "text")
    found = decontamination.contamination(keyed, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    bad = found.where("contaminated").select(F.col("doc_id").alias("_bad")).distinct()
    return _documents(docs.join(bad, _row() == F.col("_bad"), "left_anti"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Training sequences of at most 2048 tokens, as one row per piece; a null text is an empty one."""
    return packing.pack(docs)


STAGES = [
    ("language_id", language_id),
    ("line_dedup", line_dedup),
    ("near_dedup", near_dedup),
    ("decontamination", decontaminate),
    ("packing", pack),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = written(docs, f"stage-{name}")
    return docs
