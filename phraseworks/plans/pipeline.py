"""The whole method in one call, and the stage tables that queries and measures share."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text
from ..functions.stem import stem_vocabulary
from ..operators import baselines, mining, packed, rank, segment, topics
from ..sources.io import discard, scan, settle
from .oracles import SWEEPS


@dataclass(frozen=True)
class Config:
    """Support, threshold, lengths and model of one run. stem=True mines and models stems and shows the most frequent written forms;
    optimise_every=n re-estimates the priors after every n-th sweep (0: never)."""

    min_support: float = 10
    support_kind: str = "absolute"
    max_len: int | None = None
    sig_threshold: float = 3.0
    n_topics: int = 4
    sweeps: int = 20
    doc_prior: float = 0.5
    word_prior: float = 0.01
    mode: str = "partitioned"
    seed: int = 7
    stem: bool = False
    optimise_every: int = 0


@dataclass
class Stages:
    """Stage tables of one corpus (doc_id, text, lang, ...), each made once and kept in the shared folder."""

    docs: DataFrame
    config: Config = field(default_factory=Config)

    @cached_property
    def raw(self) -> DataFrame:
        return text.chunk(self.docs, keep=tuple(c for c in ("lang", "source") if c in self.docs.columns))

    @cached_property
    def chunks(self) -> DataFrame:
        kept = text.drop_stopwords(self.raw) if "lang" in self.docs.columns else self.raw.withColumn("at", F.sequence(F.lit(0), F.size("toks") - 1))
        if not self.config.stem:
            return settle(kept, "chunks")
        kept = settle(kept, "unstemmed")
        words = kept.select(F.explode("toks").alias("word")).distinct()
        return settle(text.apply_stems(kept, settle(stem_vocabulary(words), "stems")), "chunks")

    @cached_property
    def mined(self) -> mining.Mined:
        c = self.config
        return mining.frequent_phrases(self.chunks, c.min_support, c.max_len, c.support_kind)

    @cached_property
    def parts(self) -> DataFrame:
        return settle(segment.partition(self.chunks, self.mined, self.config.sig_threshold), "partition")

    @cached_property
    def cliques(self) -> DataFrame:
        return topics.make_cliques(self.parts)

    @cached_property
    def state(self) -> DataFrame:
        """Topics before the first sweep."""
        return settle(topics.init(self.cliques, self.config.n_topics, self.config.seed), "state")

    @cached_property
    def fitted(self) -> DataFrame:
        """Topics after a few sweeps that other engines can repeat: the state that measures and rankings are shown on."""
        c = self.config
        if self.parts.where("doc_id IS NULL").isEmpty():
            return packed.snapshot_cliques(self.parts, c.n_topics, SWEEPS, c.seed, c.doc_prior, c.word_prior)
        return self._swept(self.state)

    @cached_property
    def fitted_words(self) -> DataFrame:
        """The same of the word model: doc_id, chunk_no, pos, g, word, z."""
        return packed.rows(self.fitted_docs)

    @cached_property
    def sampled_docs(self) -> DataFrame:
        """The word model after all sweeps of the sampler, a row a document."""
        c = self.config
        model = baselines.lda(self.chunks, n_topics=c.n_topics, sweeps=c.sweeps, doc_prior=c.doc_prior, word_prior=c.word_prior, seed=c.seed)
        return packed.pack(baselines.tokens_with_topics(self.chunks, model))

    @cached_property
    def fitted_docs(self) -> DataFrame:
        """The word model's state, a row a document."""
        c = self.config
        return packed.snapshot(self.chunks, c.n_topics, SWEEPS, c.seed, c.doc_prior, c.word_prior)

    def _swept(self, state: DataFrame) -> DataFrame:
        c = self.config
        v = state.select(F.explode("words").alias("word")).distinct().count()
        first = state
        for s in range(1, SWEEPS + 1):
            before, state = state, settle(topics.snapshot_sweep(state, c.n_topics, s, c.seed, doc_prior=c.doc_prior, word_prior=c.word_prior, vocabulary=v), f"swept-{s}")
            if before is not first:
                discard(before)
        return state

    @cached_property
    def words(self) -> DataFrame:
        """One-word cliques with topics before the first sweep: doc_id, chunk_no, pos, word, z."""
        from pyspark.sql import Window

        rows = self.chunks.select("doc_id", "chunk_no", F.posexplode("toks").alias("pos", "word")).withColumn("g", F.row_number().over(Window.partitionBy("doc_id").orderBy("chunk_no", "pos")) - 1)
        return settle(topics.init(rows, self.config.n_topics, self.config.seed), "words")

    @cached_property
    def surfaces(self) -> DataFrame:
        at = self.chunks.select("doc_id", "chunk_no", "at")
        parts, known = self.parts, None
        if not self.config.stem:  # a single word is written as it is
            parts, known = parts.where("len > 1"), parts.where("len = 1").select("phrase", F.col("phrase").alias("surface"))
        spans = parts.join(at, ["doc_id", "chunk_no"]).select("doc_id", "chunk_no", "phrase", F.get("at", F.col("start")).alias("first_at"), F.get("at", F.col("start") + F.col("len") - 1).alias("last_at"))
        return text.surface(self.raw, spans, known)

    @cached_property
    def word_surfaces(self) -> DataFrame:
        return text.word_surfaces(self.raw, self.chunks)

    def view(self, state: DataFrame) -> DataFrame:
        """Topic view in written forms."""
        return rank.topic_view(state, surfaces=self.surfaces, word_surfaces=self.word_surfaces if self.config.stem else None)

    def fit(self, **options) -> topics.Model:
        c = self.config
        return topics.fit(self.cliques, **{"n_topics": c.n_topics, "sweeps": c.sweeps, "doc_prior": c.doc_prior, "word_prior": c.word_prior, "mode": c.mode, "seed": c.seed, "optimise_every": c.optimise_every} | options)


def run(docs: DataFrame, config: Config | None = None) -> tuple[DataFrame, Stages, topics.Model]:
    """Topic view, stage tables and model of a corpus (doc_id, text[, lang])."""
    stages = Stages(docs, config or Config())
    model = stages.fit()
    return stages.view(model.state), stages, model


_KEPT: dict[tuple, Stages] = {}


def stages_of(spark: SparkSession, sf_dir: str, max_len: int | None = None, docs: Callable[[SparkSession, str], DataFrame] | None = None, **options) -> Stages:
    """Stage tables of the documents in sf_dir, or of the corpus that ``docs`` makes of it, shared by the queries of one application."""
    key = (spark.sparkContext.applicationId, sf_dir, max_len, getattr(docs, "__name__", None), tuple(sorted(options.items())))
    if key not in _KEPT:
        corpus = docs(spark, sf_dir) if docs else scan(spark, sf_dir, "documents", "doc_id", "text", "lang", "source")
        _KEPT[key] = Stages(corpus, Config(max_len=max_len, **options))
    return _KEPT[key]


def forget() -> None:
    """Let the next queries make their stage tables anew (benches)."""
    _KEPT.clear()
