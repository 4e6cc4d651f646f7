"""A training corpus from the documents table: five stages, each written as Parquet and reread by the next.

quality classifier -> line dedup -> near-duplicate groups -> source mix -> packing. All
stages but the last return the columns of documents. SQL cannot express the first, third
and last stage, so ORACLE_SQL is None. Tests hold the operators against brute force on small
tables of their own; of the stages here they check rows, column names and counts only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockmatch.llm.common import SPACE, Workspace, fold
from blockmatch.llm.hyperminhash import drop_near_duplicates
from blockmatch.llm.lines import dedup_lines
from blockmatch.llm.mixing import mix_documents
from blockmatch.llm.packing import pack_documents, vocabulary_path
from blockmatch.llm.quality import fit_from, keep_quality


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier accepts; null and empty texts are scored too. Labels of the held-out quarter aren't learned."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return keep_quality(docs, fit_from(docs, labels, fold(F.col("doc_id"), 4) != 2))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without boilerplate lines; one that consisted of such lines alone goes."""
    had = F.coalesce(F.length(F.regexp_replace("text", SPACE, "")), F.lit(0)) > 0
    rows = dedup_lines(docs.withColumn("_had", had)).filter(~F.col("_had") | had).drop("_had")
    if "n_chars" in docs.columns:
        rows = rows.withColumn("n_chars", F.coalesce(F.char_length("text"), "n_chars").cast(docs.schema["n_chars"].dataType))
    return rows.select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each near-duplicate group."""
    return drop_near_duplicates(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the source mix takes them."""
    return mix_documents(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents with their place in sequences of 4096 tokens."""
    return pack_documents(docs, vocabulary_path("word_bpe_49k.json"))


STAGES = [("quality", quality), ("lines", line_dedup), ("near_duplicates", near_dedup), ("mix", mix), ("pack", pack)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ws = Workspace(spark, "corpus")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = ws.save(stage(spark, docs, sf_dir), name)
    return docs
