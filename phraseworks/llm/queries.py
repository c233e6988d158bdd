"""The operators' queries over the given tables, with SQL for those that SQL can express."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann_search, byte_bpe, exact_search, language_id, line_dedup, lm_scoring, packing, simhash, token_counts, url_filters, url_table
from .common import doc_hash, table

RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
VOCABULARY = public_tokenizers.path("byte_bpe_50k.json")
#: Personal data that op8 masks: mail addresses, then runs of digits.
MASKS = [(r"[\w.+-]+@[\w-]+(?:\.[\w-]+)+", "<email>", "@"), (r"\d{3,}(?:[ .-]?\d{2,})+", "<number>", "")]
MIN_SITES = 10
RULES = [url_filters.Rule("net", "/", "block"), url_filters.Rule("example.net", "/en/", "allow"), url_filters.Rule("example.com", "/de/", "block"), url_filters.Rule("org", "/fr/", "allow")]


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_bpe.digests(table(spark, sf_dir, "documents"), RANKS, public_tokenizers.PATTERN)


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"), shingle=4, limit=4)


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_lines (non-blank), dropped_lines, kept_md5 of the text that stays."""
    kept = line_dedup.drop_boilerplate(table(spark, sf_dir, "documents").select("doc_id", "text", "source"), MIN_SITES)
    left = F.size(F.filter(F.split(F.coalesce("text", F.lit("")), "\n", -1), lambda x: F.length(F.trim(x, F.lit(" \t\r"))) > 0))
    return kept.select("doc_id", (left + F.col("dropped_lines")).cast("long").alias("n_lines"), "dropped_lines", F.md5("text").alias("kept_md5"))


OP3_SQL = f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, text, source FROM documents),
l AS (SELECT r, doc_id, source, unnest(string_split(text, chr(10))) AS line, unnest(range(len(string_split(text, chr(10))))) AS pos FROM d),
k AS (SELECT *, trim(line, ' ' || chr(9) || chr(13)) AS key FROM l),
b AS (SELECT key, min(doc_id) AS keeper FROM k WHERE key <> '' GROUP BY key HAVING count(DISTINCT source) >= {MIN_SITES}),
m AS (SELECT k.*, (key <> '' AND b.keeper IS NOT NULL AND doc_id > b.keeper) AS gone FROM k LEFT JOIN b USING (key)),
g AS (SELECT r, count(*) FILTER (WHERE key <> '') AS n_lines, count(*) FILTER (WHERE gone) AS dropped, coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '') AS kept FROM m GROUP BY r)
SELECT d.doc_id, coalesce(g.n_lines, 0) AS n_lines, coalesce(g.dropped, 0) AS dropped_lines, CASE WHEN d.text IS NULL THEN NULL ELSE md5(g.kept) END AS kept_md5 FROM d LEFT JOIN g USING (r)
"""


def op4_exact_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_search.top_products(table(spark, sf_dir, "embeddings"), F.col("id") % 100 == 0)


OP4_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)) AS e FROM embeddings
           WHERE len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id, list_dot_product(q.e, c.e)::BIGINT AS score FROM v q JOIN v c ON q.vec_id % 100 = 0 AND q.vec_id <> c.vec_id),
r AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank, vec_id, score FROM s)
SELECT * FROM r WHERE rank <= 10
"""


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), VOCABULARY, capacity=1024, end_id=2)


def op6_ann_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann_search.nearest(table(spark, sf_dir, "embeddings"), F.col("id") % 50 == 0)


def op7_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scoring.score(table(spark, sf_dir, "documents"), doc_hash("doc_id") % 5 != 1)


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_masked(table(spark, sf_dir, "documents"), RANKS, public_tokenizers.PATTERN, MASKS)


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    fold = doc_hash("doc_id") % 4
    judged = language_id.predict(docs, language_id.fit(docs, fold != 2), ["doc_id"])
    return judged.select("doc_id", (doc_hash("doc_id") % 4 == 2).alias("held_out"), "lang_pred", "score", "rejected")


def op10_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    labelled = [(*url_filters.split(u), y) for u, y in url_table.labelled()]
    return url_filters.judge(table(spark, sf_dir, "pages"), RULES, url_filters.train(labelled))


def queries() -> dict:
    return {f.__name__: f for f in (op1_byte_bpe, op2_simhash, op3_line_dedup, op4_exact_search, op5_packing, op6_ann_search, op7_lm_scoring, op8_token_counts, op9_language_id, op10_url_filters)}


def oracle_sql() -> dict[str, str]:
    return {"op3_line_dedup": OP3_SQL, "op4_exact_search": OP4_SQL}
