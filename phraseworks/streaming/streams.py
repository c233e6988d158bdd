"""Streaming counterparts: the same columns as their batch twins, in Structured Streaming.

Counts of phrases keep every n-gram seen, since one below the support now may reach it later; the support is applied on reading.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text
from ..operators import mining, segment

#: Frozen phrases or words that may travel with a stream's tasks; more of them are joined.
SHIPPED = 2_000_000


def documents(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    """Documents of Parquet files as they arrive in a folder."""
    return spark.readStream.schema("doc_id BIGINT, text STRING, lang STRING, source STRING, n_chars BIGINT").option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def ngram_counts(docs: DataFrame, max_len: int = 3) -> DataFrame:
    """n, phrase, cnt: the stream's running counts (update or complete mode)."""
    return mining.all_ngrams(text.chunk(docs), max_len)


def merge_counts(folder: str, max_len: int = 3) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: adds a batch's counts to a table of versions in ``folder``. A batch that is run again writes the same
    version again, from the version before it, so nothing counts twice."""

    def merge(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        new = ngram_counts(batch, max_len)
        if batch_id:
            old = spark.read.schema("n INT, phrase STRING, cnt BIGINT").parquet(f"{folder}/v={batch_id - 1}")
            new = old.unionByName(new.select(F.col("n").cast("int").alias("n"), "phrase", "cnt")).groupBy("n", "phrase").agg(F.sum("cnt").alias("cnt"))
        new.select(F.col("n").cast("int").alias("n"), "phrase", "cnt").write.mode("overwrite").parquet(f"{folder}/v={batch_id}")

    return merge


def merged(spark: SparkSession, folder: str, batch_id: int, min_support: int = 1) -> DataFrame:
    return spark.read.schema("n INT, phrase STRING, cnt BIGINT").parquet(f"{folder}/v={batch_id}").where(F.col("cnt") >= min_support)


def timed(events: DataFrame, at: str = "ts") -> DataFrame:
    """events with a time that watermarks take: times without a zone are read in the session's."""
    return events.withColumn(at, F.col(at).cast("timestamp"))


def event_windows(events: DataFrame, size: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """start, event_type, n in tumbling or sliding windows; rows later than the watermark are dropped."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return timed(events).withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def event_sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """user_id, start, n of sessions that a gap closes."""
    return timed(events).withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(docs: DataFrame, key: str, at: str, late: str = "1 hour") -> DataFrame:
    """Rows with a key not seen within the watermark."""
    return timed(docs, at).withWatermark(at, late).dropDuplicatesWithinWatermark([key])


def user_sequences(events: DataFrame, n: int = 2, gap_seconds: int = 1800) -> DataFrame:
    """user_id, phrase: every run of n actions of one user with no gap between neighbours, over the borders of micro-batches. A
    user's state is the last n - 1 actions and their times; it goes when the gap has passed in event time. Rows more than an hour
    behind the latest row of an earlier batch are late and dropped, so files that arrive out of the order of their times lose
    rows: write them in order, or set maxFilesPerTrigger so that a batch holds all that may overtake each other."""

    def run(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        tail: list[tuple[float, str]] = []
        if state.hasTimedOut:
            state.remove()
            return
        if state.exists:
            (times, kinds) = state.get
            tail = list(zip(times, kinds, strict=True))
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        out = []
        for at, kind in zip(rows["ts"].map(lambda t: t.timestamp()), rows["event_type"], strict=True):
            if tail and at - tail[-1][0] >= gap_seconds:
                tail = []
            tail.append((at, kind))
            if len(tail) >= n:
                out.append(" ".join(k for _, k in tail[-n:]))
            tail = tail[-(n - 1) :] if n > 1 else []
        state.update(([a for a, _ in tail], [k for _, k in tail]))
        if tail and tail[-1][0] * 1000 + gap_seconds * 1000 > state.getCurrentWatermarkMs():
            state.setTimeoutTimestamp(int(tail[-1][0] * 1000) + gap_seconds * 1000)
        yield pd.DataFrame({"user_id": [key[0]] * len(out), "phrase": out})

    rows = timed(events).select("event_id", "ts", "user_id", "event_type").withWatermark("ts", "1 hour")
    return rows.groupBy("user_id").applyInPandasWithState(run, "user_id long, phrase string", "times array<double>, kinds array<string>", "append", "EventTimeTimeout")


def segmented(docs: DataFrame, counts: DataFrame, tokens: int, threshold: float) -> DataFrame:
    """doc_id, chunk_no, start, phrase of arriving documents, by counts (n, phrase, cnt) that are frozen at the start: up to SHIPPED
    phrases go with the tasks; of a larger table each micro-batch joins those that its own chunks may hold."""
    longest = counts.agg(F.max("n")).first()[0] or 1
    chunks = text.chunk(docs)
    few = counts.count() <= SHIPPED
    if few:
        known = {r["phrase"]: r["cnt"] for r in counts.select("phrase", "cnt").toLocalIterator()}
        rows = chunks.select("doc_id", "chunk_no", "toks", F.lit(None).cast("map<string,bigint>").alias("known"))
    else:
        # a chunk's own n-grams; duplicates of (doc, chunk) in a batch meet in one group with the same tokens
        grams = F.array_distinct(F.flatten(F.array(*[mining.ngrams_of(F.col("toks"), n) for n in range(1, longest + 1)])))
        rows = chunks.select("doc_id", "chunk_no", "toks", F.explode(grams).alias("gram")).join(counts.select("phrase", "cnt"), F.col("gram") == F.col("phrase"), "left")
        rows = rows.groupBy("doc_id", "chunk_no", "toks").agg(F.map_from_entries(F.collect_set(F.when(F.col("cnt").isNotNull(), F.struct("gram", "cnt")))).alias("known"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            out = []
            for doc, no, toks, own in zip(f["doc_id"], f["chunk_no"], f["toks"], f["known"], strict=True):
                toks, look = list(toks), known if few else dict(own)
                spans = {(i, m): c for i in range(len(toks)) for m in range(1, min(longest, len(toks) - i) + 1) if (c := look.get(" ".join(toks[i : i + m])))}
                units, _ = segment.merge_chunk(len(toks), spans, threshold, tokens)
                out += [(doc, no, a, " ".join(toks[a : a + m])) for a, m in units]
            yield pd.DataFrame(out, columns=["doc_id", "chunk_no", "start", "phrase"])

    return rows.mapInPandas(run, "doc_id long, chunk_no int, start int, phrase string")


def inferred(chunks: DataFrame, phis: dict[str, list[float]] | DataFrame, n_topics: int, doc_prior: float = 0.5, rounds: int = 10) -> DataFrame:
    """doc_id, chunk_no, theta of arriving chunks under frozen word distributions, by repeated expectation. A dict (word -> a
    probability a topic) of up to SHIPPED words goes with the tasks, so the stream is stateless; a table (word, phi array) is
    joined and needs foreachBatch or update mode."""
    joined = not isinstance(phis, dict) or len(phis) > SHIPPED
    if joined:
        table = phis if not isinstance(phis, dict) else chunks.sparkSession.createDataFrame(list(phis.items()), "word string, phi array<double>")
        words = chunks.select("doc_id", "chunk_no", F.explode("toks").alias("word")).join(table, "word", "left")
        rows = words.groupBy("doc_id", "chunk_no").agg(F.collect_list("phi").alias("likes"))
    else:
        rows = chunks.select("doc_id", "chunk_no", F.col("toks").alias("likes"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import numpy as np

        for f in frames:
            out = []
            for likes in f["likes"]:
                like = np.array([list(x) for x in likes] if joined else [phis[t] for t in likes if t in phis])
                th = np.full(n_topics, 1 / n_topics)
                for _ in range(rounds if len(like) else 0):
                    share = like * th
                    th = doc_prior + (share / share.sum(1, keepdims=True)).sum(0)
                    th = th / th.sum()
                out.append(th.tolist())
            yield pd.DataFrame({"doc_id": f["doc_id"], "chunk_no": f["chunk_no"], "theta": out})

    return rows.mapInPandas(run, "doc_id long, chunk_no int, theta array<double>")


def clicks_to_purchases(events: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """click_id, purchase_id: purchases that follow a click of the same user in time; both sides' states end with the watermarks. Rows
    later than ``late`` behind the latest of an earlier batch are dropped, as in ``user_sequences``."""
    events = timed(events)
    a = events.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u"), F.col("ts").alias("t0")).withWatermark("t0", late)
    b = events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("ts").alias("t1")).withWatermark("t1", late)
    return a.join(b, F.expr(f"u = user_id AND t1 > t0 AND t1 <= t0 + INTERVAL {within}")).select("click_id", "purchase_id")
