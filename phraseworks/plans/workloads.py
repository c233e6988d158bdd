"""The experiment corpora on the given tables: (doc_id, text[, lang, source])."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text
from ..sources.io import scan


def share(doc_id: Column) -> Column:
    """A number in [0, 1) by the md5 of an id, for samples that are the same everywhere."""
    return F.conv(F.substring(F.md5(doc_id.cast("string")), 1, 8), 16, 10).cast("double") / 4294967296.0


def first_line(t: Column) -> Column:
    return F.get(F.split(t, "\n", -1), F.lit(0))


def titles(spark: SparkSession, sf_dir: str, fraction: float = 1.0) -> DataFrame:
    """Short texts: each document's first chunk, page titles and part names, or a hash sample of them."""
    docs = scan(spark, sf_dir, "documents", "doc_id", "text", "lang")
    firsts = docs.select(F.concat(F.lit("d"), F.col("doc_id")).alias("key"), F.get(F.filter(F.split(F.lower("text"), text.BOUNDARY, -1), lambda p: F.trim(p) != ""), F.lit(0)).alias("text"), "lang")
    pages = scan(spark, sf_dir, "pages", "page_id", "html").select(F.concat(F.lit("p"), F.col("page_id")).alias("key"), text.page_title(F.col("html")).alias("text"), F.regexp_extract("html", r'<html lang="(\w+)"', 1).alias("lang"))
    parts = scan(spark, sf_dir, "part", "p_partkey", "p_name").select(F.concat(F.lit("n"), F.col("p_partkey")).alias("key"), F.col("p_name").alias("text"), F.lit("en").alias("lang"))
    rows = firsts.unionByName(pages).unionByName(parts).where("text is not null")
    return (rows if fraction >= 1 else rows.where(share(F.col("key")) < fraction)).withColumn("doc_id", F.xxhash64("key")).drop("key")


def sampled(docs: DataFrame, fraction: float) -> DataFrame:
    return docs.where(share(F.col("doc_id")) < fraction)


def stratified(docs: DataFrame, key: str, shares: dict[str, float]) -> DataFrame:
    """A hash sample with a share of its own for each value of key; other values have none. The same rows everywhere, unlike sampleBy's."""
    part = F.lit(0.0)
    for value, of in shares.items():
        part = F.when(F.col(key) == value, of).otherwise(part)
    return docs.where(share(F.col("doc_id")) < part)


def by_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First lines of documents; sources stand for venues."""
    return scan(spark, sf_dir, "documents", "doc_id", "text", "lang", "source").withColumn("text", first_line(F.col("text")))


def abstracts(spark: SparkSession, sf_dir: str, lang: str | None = "en") -> DataFrame:
    docs = scan(spark, sf_dir, "documents", "doc_id", "text", "lang", "source", "n_chars").where("n_chars <= 2500")
    return (docs.where(F.col("lang") == lang) if lang else docs).drop("n_chars")


def articles(spark: SparkSession, sf_dir: str) -> DataFrame:
    long = scan(spark, sf_dir, "documents", "doc_id", "text", "lang", "n_chars").where("n_chars > 2500").select(F.col("doc_id"), "text", "lang")
    pages = scan(spark, sf_dir, "pages", "page_id", "html").select((-1 - F.col("page_id")).alias("doc_id"), text.page_body(F.col("html")).alias("text"), F.regexp_extract("html", r'<html lang="(\w+)"', 1).alias("lang"))
    return long.unionByName(pages)


def reviews(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A document a conversation: its user turns in order."""
    turns = scan(spark, sf_dir, "conversations").where("role = 'user'")
    return turns.groupBy(F.col("conv_id").alias("doc_id")).agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda t: t["text"]), "\n").alias("text")).withColumn("lang", F.lit("en"))


def action_sequences(spark: SparkSession, sf_dir: str, gap: str = "30 minutes") -> DataFrame:
    """doc_id, toks: event types of one user's session, in order."""
    ev = scan(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    s = ev.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda e: e["event_type"]).alias("toks"))
    return s.select(F.xxhash64("user_id", F.col("w.start")).alias("doc_id"), "user_id", F.col("w.start").alias("start"), F.lit(0).alias("chunk_no"), "toks")


def baskets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """o, items: distinct words of the part names of each order."""
    lines = scan(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").join(scan(spark, sf_dir, "part", "p_partkey", "p_name"), F.col("l_partkey") == F.col("p_partkey"))
    return lines.select(F.col("l_orderkey").alias("o"), F.explode(F.split("p_name", " ")).alias("w")).groupBy("o").agg(F.collect_set("w").alias("items"))
