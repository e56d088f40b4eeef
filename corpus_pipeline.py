"""From raw documents to token rows: quality rules, near duplicates, benchmark overlap, mixing, token files.

Each stage takes (spark, docs, sf_dir) and gives a DataFrame, which is written as Parquet and read
again as the next one's docs. All but the last give the columns that docs has, whatever they are
called; an empty table gives an empty one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from graphwatch.functions.storage import scratch_path, table
from graphwatch.llm import decontaminate, mixing, neardup, quality, tokenfiles

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that break no rule. A null or blank text goes; rows are judged one by one, so repeated rows share their fate."""
    return quality.keep_good(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group: five-word shingles, similarity 0.8.

    The smallest doc_id of a group stays. Rows with one doc_id stay or go together; a row without a
    doc_id stays, and so does a text without words, which is in no group.
    """
    return neardup.drop_near_duplicates(docs, percent=80, width=5)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that overlap with no benchmark item. A null text overlaps with none; a row without a doc_id stays; rows with one doc_id go together."""
    return decontaminate.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Whole documents, each as often as the mix draws it, at most twice.

    A null source is a source of its own; a null or blank text is never drawn. Repeated rows are drawn
    as often as their number asks for, and which of them it is makes no difference.
    """
    return mixing.mixed_documents(docs)


def token_files(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The rows of the token files, read back from them, in ascending doc_id order, null first and ties by text. A null text is an end token alone."""
    import public_tokenizers

    path = scratch_path(spark, "tokens")
    tokenfiles.write_tokens(docs, path, public_tokenizers.path("word_bpe_49k.json"))
    return tokenfiles.read_tokens(spark, path)


STAGES = [
    ("quality rules", quality_rules),
    ("near duplicates", near_duplicates),
    ("benchmark decontamination", decontamination),
    ("source mix", source_mix),
    ("token files", token_files),
]

#: Near duplicates, hash-ordered mixing and tokenizing are not for SQL; tests compare them with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of sf_dir, each written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(*COLUMNS)
    for name, stage in STAGES:
        docs = table(stage(spark, docs, sf_dir), "stage-" + name.replace(" ", "-"))
    return docs
