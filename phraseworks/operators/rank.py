"""Ranking of words and phrases in topics, labels and filters."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def topical_frequency(state: DataFrame) -> DataFrame:
    """phrase, n_words, k, tf: instances of a phrase whose clique has topic k."""
    return state.groupBy(F.concat_ws(" ", "words").alias("phrase"), F.size("words").alias("n_words"), F.col("z").alias("k")).agg(F.count("*").alias("tf"))


def word_frequency(state: DataFrame) -> DataFrame:
    """word, k, tf in tokens."""
    return state.select(F.explode("words").alias("word"), F.col("z").alias("k")).groupBy("word", "k").agg(F.count("*").alias("tf"))


def top(rows: DataFrame, n: int, by: Column, *ties: str, group: str = "k") -> DataFrame:
    """The n best rows of each group with rank from 1; only n rows a group and task reach the shuffle."""
    return rows.withColumn("rank", F.row_number().over(Window.partitionBy(group).orderBy(by.desc(), *ties))).where(F.col("rank") <= n)


def topic_view(state: DataFrame, n_words: int = 10, n_phrases: int = 10, min_words: int = 2, surfaces: DataFrame | None = None, word_surfaces: DataFrame | None = None) -> DataFrame:
    """k, kind ('word' or 'phrase'), rank, text, score: each topic's top words and top phrases of at least min_words words.
    surfaces (phrase, surface) puts the written form in place of the mined one, word_surfaces (word, surface) does so for words."""
    words = top(word_frequency(state), n_words, F.col("tf"), "word").select("k", F.lit("word").alias("kind"), "rank", F.col("word").alias("text"), F.col("tf").alias("score"))
    phrases = top(topical_frequency(state).where(F.col("n_words") >= min_words), n_phrases, F.col("tf"), "phrase").select("k", F.lit("phrase").alias("kind"), "rank", F.col("phrase").alias("text"), F.col("tf").alias("score"))
    if surfaces is not None:
        s = surfaces.select(F.col("phrase").alias("p"), "surface")
        phrases = phrases.join(s, F.col("text") == F.col("p"), "left").select("k", "kind", "rank", F.coalesce("surface", "text").alias("text"), "score")
    if word_surfaces is not None:
        s = word_surfaces.select(F.col("word").alias("p"), "surface")
        words = words.join(s, F.col("text") == F.col("p"), "left").select("k", "kind", "rank", F.coalesce("surface", "text").alias("text"), "score")
    return words.unionByName(phrases)


def label_score(state: DataFrame, min_tf: int = 5) -> DataFrame:
    """k, phrase, kl, mi, score: how well a phrase of two or more words labels a topic.

    kl compares the topic's word distribution with that of the documents that hold the phrase, over their words; mi is the
    topic's mean of log p(word, phrase) / (p(word) p(phrase)) over the same words. score = mi - kl."""
    words = word_frequency(state)
    totals = words.groupBy("k").agg(F.sum("tf").alias("total"))
    pk = words.join(totals, "k").select("word", "k", (F.col("tf") / F.col("total")).alias("p_k"))
    cands = topical_frequency(state).where(f"n_words > 1 and tf >= {min_tf}").select("phrase").distinct()
    holders = state.where(F.size("words") > 1).select("doc_id", F.concat_ws(" ", "words").alias("phrase")).distinct().join(cands, "phrase")
    doc_words = state.select("doc_id", F.explode("words").alias("word")).groupBy("doc_id", "word").agg(F.count("*").alias("c"))
    near = holders.join(doc_words, "doc_id").groupBy("phrase", "word").agg(F.sum("c").alias("c"))
    sizes = near.groupBy("phrase").agg(F.sum("c").alias("s"))
    everything = words.groupBy("word").agg(F.sum("tf").alias("w"))
    n = totals.agg(F.sum("total").alias("n"))
    joined = near.join(sizes, "phrase").join(everything, "word").crossJoin(n).join(pk, "word")  # one row on the right
    q = F.col("c") / F.col("s")
    return joined.groupBy("k", "phrase").agg(F.sum(F.col("p_k") * F.log(F.col("p_k") / q)).alias("kl"), F.sum(F.col("p_k") * F.log(q / (F.col("w") / F.col("n")))).alias("mi")).withColumn("score", F.col("mi") - F.col("kl"))


def with_candidates(tf: DataFrame, candidates: DataFrame) -> DataFrame:
    """Only phrases that a user's table (phrase) names."""
    return tf.join(candidates.select("phrase").distinct(), "phrase", "left_semi")


def multi_facet(tf: DataFrame, scores: DataFrame, weights: tuple[float, float, float, float] = (1.0, 1.0, 0.5, 0.25)) -> DataFrame:
    """k, phrase, facet_score: weighted sum of log frequency, purity, significance and length, each scaled to 0..1 in its topic.
    scores: phrase, sig."""
    whole = Window.partitionBy("phrase")
    rows = tf.where("n_words > 1").withColumn("purity", F.col("tf") / F.sum("tf").over(whole)).join(scores, "phrase", "left").select("k", "phrase", F.log("tf").alias("f1"), F.col("purity").alias("f2"), F.coalesce("sig", F.lit(0.0)).alias("f3"), F.col("n_words").cast("double").alias("f4"))
    names = ("f1", "f2", "f3", "f4")
    # a row for each topic, so no task holds a whole topic
    spread = rows.groupBy("k").agg(*[f(n).alias(f"{m}_{n}") for n in names for m, f in (("low", F.min), ("high", F.max))])
    joined, scaled = rows.join(spread, "k"), F.lit(0.0)
    for name, w in zip(names, weights, strict=True):
        low, high = F.col(f"low_{name}"), F.col(f"high_{name}")
        scaled = scaled + w * F.when(high > low, (F.col(name) - low) / (high - low)).otherwise(0.0)
    return joined.select("k", "phrase", scaled.alias("facet_score"))


def drop_background(tf: DataFrame, n_topics: int, share: float = 0.9) -> DataFrame:
    """tf without phrases whose spread over topics has an entropy above share * ln(n_topics)."""
    q = F.col("tf") / F.sum("tf").over(Window.partitionBy("phrase"))
    import math

    rows = tf.withColumn("q", q).withColumn("h", -F.sum(F.col("q") * F.log("q")).over(Window.partitionBy("phrase")))
    return rows.where(F.round("h", 9) <= round(share * math.log(n_topics), 9)).drop("q", "h")
