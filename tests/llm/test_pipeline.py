"""The pipeline's stages on awkward rows and against a plain version of each decision."""

import collections

import corpus_pipeline
from pyspark.sql import functions as F

from phraseworks.llm import language_id
from tests.llm.test_operators import CLASHES, ROWS, brute_similar, check_packing


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = docs.columns
    steps = [docs]
    for _, stage in corpus_pipeline.STAGES:
        steps.append(stage(spark, steps[-1], sf).cache())
    one, two, three, four = steps[1:]
    assert one.columns == two.columns == three.columns == names
    model = language_id.fit(docs, F.lit(True))
    assert {r["doc_id"] for r in one.collect()} == {r["doc_id"] for r in docs.collect() if not model.judge(r["text"])[2]}
    sites, first = collections.defaultdict(set), {}
    for r in one.collect():
        for line in r["text"].split("\n"):
            key = line.strip(" \t\r")
            if key:
                sites[key].add(r["source"])
                first[key] = min(first.get(key, r["doc_id"]), r["doc_id"])
    bad = {k for k, s in sites.items() if len(s) >= 10}
    want = {r["doc_id"]: "\n".join(x for x in r["text"].split("\n") if not (x.strip(" \t\r") in bad and r["doc_id"] > first[x.strip(" \t\r")])) for r in one.collect()}
    assert {r["doc_id"]: r["text"] for r in two.collect()} == want
    texts = {r["doc_id"]: r["text"] for r in two.collect()}
    of = dict(zip(texts, brute_similar(list(texts.values())), strict=True))
    kept = {r["doc_id"] for r in three.collect()}
    assert three.count() == len(kept) and {of[i] for i in kept} == set(of.values())  # every group has a document left
    assert len(kept) <= 1.01 * len(set(of.values()))
    alone = collections.Counter(of.values())
    assert all(i in kept for i in texts if alone[of[i]] == 1)
    rows = four.collect()
    check_packing(rows, 1024)
    assert {r["doc_id"] for r in rows} == {r["doc_id"] for r in three.collect()}
    assert corpus_pipeline.run(spark, sf).count() == len(rows)


def test_awkward_rows(spark, sf):
    docs = spark.createDataFrame(ROWS, "doc_id long, text string, lang string, source string").withColumn("n_chars", F.length("text").cast("long")).select("*", *[F.lit("c").alias(c) for c in CLASHES])
    for start in (docs, docs.limit(0)):
        df = start
        for _, stage in corpus_pipeline.STAGES:
            df = stage(spark, df, sf)
        df.collect()


def test_unlike_texts_under_one_id(spark, sf):
    """A repeated id makes no document of another's text go."""
    text = lambda a: " ".join(f"{a}{i}" for i in range(60))
    rows = [(3, text("a")), (3, text("b")), (10, text("a") + " end"), (11, text("b") + " end")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "'en' AS lang", "'s' AS source", "cast(length(text) AS long) AS n_chars")
    kept = corpus_pipeline.drop_near_duplicates(spark, docs, sf)
    assert sorted(r["text"] for r in kept.collect()) == [text("a"), text("b")]
