"""The compared methods go through all of their steps."""

import functools
import inspect

import numpy as np
from pyspark.sql import functions as F

from phraseworks.operators import baselines, packed
from phraseworks.plans import methods, pipeline
from phraseworks.plans.queries import QUERIES


def _watch(monkeypatch, name, seen):
    work = getattr(baselines, name)

    @functools.wraps(work)
    def watched(*args, **options):
        seen[name] = inspect.signature(work).bind(*args, **options).arguments
        return work(*args, **options)

    monkeypatch.setattr(baselines, name, watched)


def test_compared_models_have_equal_sweeps(spark, monkeypatch):
    """Each model of the comparison goes through all of the sweeps, the slow ones too."""
    seen = {}
    for name in ("lda", "bigram_switch", "pitman_yor_phrases"):
        _watch(monkeypatch, name, seen)
    rows = [(d, "red apple pie . green tea leaf" if d % 2 else "blue sky line . cold sea wave", "en") for d in range(12)]
    stages = pipeline.Stages(spark.createDataFrame(rows, "doc_id long, text string, lang string"), pipeline.Config(min_support=2, sig_threshold=1.0, n_topics=2))
    assert {r.method for r in methods.lists(stages, sweeps=4, n_perm=5, min_support=2).collect()} <= set(methods.METHODS)
    got = {name: a["sweeps"] if "sweeps" in a else a["options"]["sweeps"] for name, a in seen.items()}
    assert got == {"lda": 4, "bigram_switch": 4, "pitman_yor_phrases": 4}


def test_posthoc_merging_follows_the_fitted_model(spark, monkeypatch, tmp_path):
    """The query merges words of the fitted word model, in which a document of one theme has one topic, not of the start by chance."""
    rng = np.random.default_rng(5)
    rows = [(d, " ".join(f"w{8 * (d % 4) + i}" for i in rng.integers(0, 8, 40)), "en", "src0") for d in range(60)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    seen = {}
    _watch(monkeypatch, "posthoc_docs", seen)
    QUERIES["posthoc_merge"](spark, str(tmp_path))
    docs = seen["posthoc_docs"]["docs"]
    shares = [max(np.bincount(r.z)) / len(r.z) for r in docs.collect()]
    assert len(shares) == 60 and np.mean(shares) > 0.85
    assert packed.rows(docs).groupBy("word").count().count() == 32


def test_posthoc_merging_goes_on_until_no_pair_is_significant(spark):
    """A passage of 40 words in every document grows beyond the eight words that three rounds can join."""
    rng = np.random.default_rng(6)
    fill = lambda: [f"w{i}" for i in rng.integers(0, 5, 10)]
    rows = [(d, 0, [*fill(), *[f"p{i}" for i in range(40)], *fill()]) for d in range(60)]
    chunks = spark.createDataFrame(rows, "doc_id long, chunk_no int, toks array<string>")
    tokens = chunks.select("doc_id", "chunk_no", F.posexplode("toks").alias("pos", "word")).withColumn("z", F.lit(0))
    merged = baselines.posthoc_merge(tokens, n_perm=5)
    assert merged.agg(F.max(F.size(F.split("word", " ")))).first()[0] > 8
