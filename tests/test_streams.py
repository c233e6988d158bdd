"""Streams give what their batch twins give."""

import os

import pytest
from pyspark.sql import functions as F

from phraseworks.functions import text
from phraseworks.operators import mining, segment
from phraseworks.plans import workloads
from phraseworks.sources import io
from phraseworks.streaming import streams


@pytest.fixture(scope="module")
def event_files(spark, sf, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("events"))
    write_in_order(io.scan(spark, sf, "events").orderBy("ts", "event_id").toPandas(), folder, range(4))
    return folder


def write_in_order(rows, folder, order):
    """Quarters of the rows as files, numbered by time; the source takes them by their modification times, in the given order."""
    for nth, part in enumerate(order):
        cut = [len(rows) * i // 4 for i in range(5)]
        path = f"{folder}/part-{part}.parquet"
        rows.iloc[cut[part] : cut[part + 1]].to_parquet(path, coerce_timestamps="us")
        os.utime(path, (1_700_000_000 + nth, 1_700_000_000 + nth))


@pytest.fixture(scope="module")
def doc_files(spark, sf, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("docs"))
    io.scan(spark, sf, "documents").repartition(3).write.mode("overwrite").parquet(folder)
    return folder


def drain(df, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def events(spark, folder):
    return spark.readStream.schema(spark.read.parquet(folder).schema).option("maxFilesPerTrigger", 1).parquet(folder)


def test_windows(spark, sf, event_files):
    drain(streams.event_windows(events(spark, event_files), "1 day"), "win", "complete")
    want = io.scan(spark, sf, "events").groupBy(F.window("ts", "1 day").alias("w"), "event_type").count().select("w.start", "event_type", "count")
    assert {tuple(r) for r in spark.table("win").collect()} == {tuple(r) for r in want.collect()}


def test_user_sequences(spark, sf, event_files):
    drain(streams.user_sequences(events(spark, event_files), 2, 86_400), "seqs")
    want = mining.all_ngrams(workloads.action_sequences(spark, sf, "1 day").withColumn("doc_id", F.col("doc_id")), 2).where("n = 2")
    got = spark.table("seqs").groupBy("phrase").count()
    assert {tuple(r) for r in got.collect()} == {(r["phrase"], r["cnt"]) for r in want.collect()}


def test_files_out_of_order_lose_late_rows(spark, sf, tmp_path):
    """A file that comes after later ones holds late rows: they are dropped, and nothing else is."""
    rows = io.scan(spark, sf, "events").orderBy("ts", "event_id").toPandas()
    write_in_order(rows, str(tmp_path), [0, 3, 1, 2])
    drain(streams.user_sequences(events(spark, str(tmp_path)), 1, 86_400), "late_seqs")
    cut = [len(rows) * i // 4 for i in range(5)]
    kept = rows.iloc[[*range(cut[0], cut[1]), *range(cut[3], cut[4])]]
    got = {r["user_id"]: r["count"] for r in spark.table("late_seqs").groupBy("user_id").count().collect()}
    most, least = rows.groupby("user_id").size().to_dict(), kept.groupby("user_id").size().to_dict()
    assert sum(got.values()) < len(rows) and all(least.get(u, 0) <= n <= most[u] for u, n in got.items()) and set(least) <= set(got)
    drain(streams.clicks_to_purchases(events(spark, str(tmp_path))), "late_join")
    ev = io.scan(spark, sf, "events")
    a, b = ev.where("event_type = 'click'").alias("a"), ev.where("event_type = 'purchase'").alias("b")
    every = {tuple(r) for r in a.join(b, F.expr("a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")).select("a.event_id", "b.event_id").collect()}
    assert {tuple(r) for r in spark.table("late_join").collect()} < every


def test_interval_join(spark, sf, event_files):
    drain(streams.clicks_to_purchases(events(spark, event_files)), "joined")
    ev = io.scan(spark, sf, "events")
    a, b = ev.where("event_type = 'click'").alias("a"), ev.where("event_type = 'purchase'").alias("b")
    want = a.join(b, F.expr("a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")).select("a.event_id", "b.event_id")
    assert {tuple(r) for r in spark.table("joined").collect()} == {tuple(r) for r in want.collect()}


def test_counts_and_segments(spark, sf, doc_files, tmp_path):
    folder = f"file://{tmp_path}/counts"
    q = streams.documents(spark, doc_files).writeStream.foreachBatch(streams.merge_counts(folder, 2)).trigger(availableNow=True).start()
    q.awaitTermination()
    last = max(p["batchId"] for p in q.recentProgress)
    docs = io.scan(spark, sf, "documents")
    want = mining.all_ngrams(text.chunk(docs), 2)
    got = streams.merged(spark, folder, last)
    assert got.exceptAll(want.select("n", "phrase", "cnt")).count() == 0 and got.count() == want.count()

    chunks = text.chunk(docs)
    mined = mining.frequent_phrases(chunks, 10, 3)
    drain(streams.segmented(streams.documents(spark, doc_files), mined.counts, mined.tokens, 3.0), "segs")
    want = segment.partition(chunks, mined, 3.0).select("doc_id", "chunk_no", "start", "phrase")
    assert spark.table("segs").exceptAll(want).count() == 0 and spark.table("segs").count() == want.count()


def test_inference_and_dedup(spark, doc_files, event_files):
    chunks = text.chunk(streams.documents(spark, doc_files))
    drain(streams.inferred(chunks, {"the": [0.9, 0.1], "de": [0.1, 0.9]}, 2), "inferred")
    assert spark.table("inferred").where("abs(theta[0] + theta[1] - 1) > 1e-9").count() == 0
    ev = events(spark, event_files)
    drain(streams.deduplicated(ev.unionByName(ev), "event_id", "ts", "40 days"), "once")
    assert spark.table("once").count() == spark.read.parquet(event_files).count()
