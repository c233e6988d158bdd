"""Corpus pipeline: language ID, line dedup, SimHash near-dedup, best-fit packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phraseworks.llm import language_id, line_dedup, packing, queries, simhash
from phraseworks.llm.common import settle

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def keep_known_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that language ID rejects go: those without a letter, null ones included, and those it is not sure of. The others
    keep all their columns. Without any labelled row nothing can be judged, and all go."""
    model = language_id.fit(docs, F.lit(True))
    return language_id.predict(docs, model, COLUMNS).where(~F.col("rejected")).select(*COLUMNS)


def drop_boilerplate_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Boilerplate lines go from all documents but the first that has them; n_chars follows the text."""
    kept = line_dedup.drop_boilerplate(docs.select(*COLUMNS), queries.MIN_SITES)
    return kept.withColumn("n_chars", F.when(F.col("dropped_lines") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of texts that links of 0.8 or more on five-word shingles join, the document with the least id stays (null ids
    come last; of rows that repeat an id and its text one stays). Unlike texts under one id are different documents."""
    return simhash.one_of_each(docs.select(*COLUMNS), shingle=5, similar=0.8)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents with their places in sequences of 1024 tokens; a null text is empty and has its end id alone."""
    return packing.pack_documents(docs, queries.VOCABULARY, capacity=1024, end_id=2)


STAGES = [("language_id", keep_known_languages), ("line_dedup", drop_boilerplate_lines), ("simhash_near_dedup", drop_near_duplicates), ("best_fit_packing", pack)]
#: The first stage is a trained model, so SQL can't express run()'s rows; tests hold them against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(*COLUMNS)
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = settle(docs, name)
    return docs
