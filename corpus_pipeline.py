"""The corpus pipeline: language identification, near-duplicates, decontamination, secrets, packing.

Every stage takes (spark, docs, sf_dir), works on all that the stage before it kept, and
gives the columns of documents back; the last one gives packed sequences. Between
stages documents are written as Parquet and read again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulegraph.llm.common import free_name, staged, table
from rulegraph.llm.decontaminate import cut_passages
from rulegraph.llm.language import fit, with_language
from rulegraph.llm.neardup import keep_first
from rulegraph.llm.packing import pack
from rulegraph.llm.queries import vocabulary_path
from rulegraph.llm.secrets import redact_column
from rulegraph.session import ship

#: A text whose best language holds less than this mean posterior is in no known language.
LEAST_SCORE = 0.3


def _measured(docs: DataFrame) -> DataFrame:
    """n_chars follows the text where a stage changed it."""
    return docs.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else docs


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects texts without letters or in no known language; the model learns from the labelled rows of docs."""
    ship(spark)
    label, score = free_name(docs.columns, "label"), free_name(docs.columns, "score")
    judged = with_language(docs, fit(docs), label, score)
    return judged.where((F.col(label) != "und") & (F.col(score) >= LEAST_SCORE)).select(*docs.columns)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates stays."""
    ship(spark)
    return keep_first(docs, threshold=0.8, size=5)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts passages of the benchmark out of texts; a text without any letter or digit left goes."""
    ship(spark)
    cut = cut_passages(docs, table(spark, sf_dir, "benchmark"), size=10)
    return _measured(cut).where(F.col("text").rlike("[\\p{L}\\p{N}]"))


def secrets_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Masks secrets in texts."""
    ship(spark)
    return _measured(redact_column(docs))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs all texts into sequences of at most 4096 ids."""
    ship(spark)
    return pack(docs, vocabulary_path(), end_id=2, room=4096)


STAGES = [
    ("language_id", language_stage),
    ("near_duplicates", near_duplicate_stage),
    ("decontamination", decontamination_stage),
    ("secrets", secrets_stage),
    ("packing", packing_stage),
]

#: SQL can express neither the model of the first stage nor the tokens of the last.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of sf_dir."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
