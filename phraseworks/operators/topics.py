"""Topic model over cliques: all words of a phrase instance share one topic. Plain LDA is the case of one-word cliques.

``snapshot`` sweeps in DataFrame operations from the counts of the sweep before, with uniform numbers from md5, so other
engines can repeat it. ``exact`` and ``partitioned`` sample in numpy: documents form blocks, and a block goes through local
counts of the words it has, its documents one after another (exact: one block, no approximation) or many side by side
(partitioned); the counts are taken anew from all blocks' topics at the end of each sweep.

Blocks are as many as keep a block's words times topics within ``BLOCK_CELLS``. While all counts are at most ``SHIP_CELLS`` they
are broadcast; beyond, each block is joined with the counts of its own words. Both ways give a block the same numbers, so the
result does not depend on the way.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.io import discard, settle

#: Counts that may be broadcast, and counts that a block may hold: words times topics.
SHIP_CELLS, BLOCK_CELLS = 20_000_000, 32_000_000
#: Words up to which a clique's weight is a plain product; that of a longer one leaves the range of numbers, so logarithms are added.
SHORT = 16
#: Cliques over which a document is drawn in pieces.
PIECE = 512


def uniform(seed: int, sweep: int, *keys: Column) -> Column:
    """A number in [0, 1) fixed by seed, sweep and keys."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit(str(sweep)), *[k.cast("string") for k in keys])), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def make_cliques(parts: DataFrame) -> DataFrame:
    """doc_id, g, words array<string> of a partition."""
    return parts.select("doc_id", "g", F.split("phrase", " ").alias("words"))


def singletons(chunks: DataFrame) -> DataFrame:
    """One-word cliques of chunks, numbered through each document."""
    rows = chunks.select("doc_id", "chunk_no", F.posexplode("toks").alias("pos", "word"))
    return rows.select("doc_id", (F.row_number().over(Window.partitionBy("doc_id").orderBy("chunk_no", "pos")) - 1).alias("g"), F.array("word").alias("words"))


def init(cliques: DataFrame, n_topics: int, seed: int = 7) -> DataFrame:
    """cliques with z, a topic fixed by the clique's place."""
    return cliques.withColumn("z", F.floor(uniform(seed, 0, F.col("doc_id"), F.col("g")) * n_topics).cast("int"))


def counts(state: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """word_topic (word, k, cnt), doc_topic (doc_id, k, cnt) and topic_total (k, cnt), all in tokens."""
    words = state.select("doc_id", "z", F.explode("words").alias("word"))
    return (words.groupBy("word", F.col("z").alias("k")).agg(F.count("*").alias("cnt")), state.groupBy("doc_id", F.col("z").alias("k")).agg(F.sum(F.size("words")).alias("cnt")), state.groupBy(F.col("z").alias("k")).agg(F.sum(F.size("words")).alias("cnt")))


def _vectors(rows: DataFrame, key: str, n_topics: int, name: str) -> DataFrame:
    """(key, k, cnt) as (key, array of n_topics counts): an expression a topic while they are few, a map for any number."""
    if n_topics > 64:
        return _dense(rows, key, n_topics, name).withColumn(name, F.col(name).cast("array<bigint>"))
    return rows.groupBy(key).agg(F.array(*[F.coalesce(F.sum(F.when(F.col("k") == k, F.col("cnt"))), F.lit(0)) for k in range(n_topics)]).alias(name))


def clique_weights(state: DataFrame, n_topics: int, doc_prior: float = 0.5, word_prior: float = 0.01, repeat_offset: bool = True, vocabulary: int | None = None) -> DataFrame:
    """doc_id, g, words, z, logs array<double>: log weight of each topic for every clique, all counts without the clique itself.

    A topic's weight is the product over the clique's words of document, word and total factors that grow by one with every word
    before. repeat_offset also counts earlier copies of the same word in the clique (the exact conditional); without it the
    factor is the published one. Both agree where no word repeats."""
    word_topic, doc_topic, _ = counts(state)
    # written, so that the joins below are planned by their true sizes and the state's rows need no shuffle while these are small
    of_word, of_doc = settle(_vectors(word_topic, "word", n_topics, "n_word"), "word-vectors"), settle(_vectors(doc_topic, "doc_id", n_topics, "n_doc"), "doc-vectors")
    v = vocabulary or of_word.count()
    totals = of_doc.select(F.posexplode("n_doc").alias("k", "cnt")).groupBy("k").agg(F.sum("cnt").alias("cnt"))
    totals = {r["k"]: r["cnt"] for r in totals.collect()}  # n_topics numbers
    total = F.array(*[F.lit(totals.get(k, 0)) for k in range(n_topics)])

    def log_weight(k: int) -> Column:
        own = (F.col("z") == k).cast("int")
        doc = F.lit(doc_prior) + F.col("n_doc")[k] - own * F.col("w") + F.col("j")
        word = F.lit(word_prior) + F.col("n_word")[k] - own * F.col("copies") + F.col("earlier")
        return F.log(doc) + F.log(word) - F.log(F.lit(word_prior * v) + total[k] - own * F.col("w") + F.col("j"))

    met = lambda rows: rows.join(of_word, "word").join(of_doc, "doc_id")
    # nearly all cliques are one word: a row each, which nothing needs to bring together
    ones = met(state.where(F.size("words") == 1).select("doc_id", "g", "z", F.lit(0).alias("j"), F.col("words")[0].alias("word"), F.lit(0).alias("earlier"), F.lit(1).alias("copies"), F.lit(1).alias("w")))
    single = ones.select("doc_id", "g", F.array("word").alias("words"), "z", F.array(*[log_weight(k) for k in range(n_topics)]).alias("logs"))
    long = state.where(F.size("words") > 1).select("doc_id", "g", "z", "words", F.posexplode("words").alias("j", "word"))
    earlier = F.size(F.filter(F.slice("words", 1, F.col("j")), lambda w: w == F.col("word"))) if repeat_offset else F.lit(0)
    copies = F.size(F.filter("words", lambda w: w == F.col("word")))
    rest = met(long.select("*", earlier.alias("earlier"), copies.alias("copies"), F.size("words").alias("w")))
    return single.unionByName(rest.groupBy("doc_id", "g").agg(F.first("words").alias("words"), F.first("z").alias("z"), F.array(*[F.sum(log_weight(k)) for k in range(n_topics)]).alias("logs")))


def probabilities(weights: DataFrame) -> DataFrame:
    """weights with probs array<double>."""
    scaled = F.transform("logs", lambda x: F.exp(x - F.array_max("logs")))
    return weights.withColumn("probs", scaled).withColumn("probs", F.transform("probs", lambda x: x / F.aggregate("probs", F.lit(0.0), lambda a, b: a + b)))


def snapshot_sweep(state: DataFrame, n_topics: int, sweep: int, seed: int = 7, **priors) -> DataFrame:
    """Every clique's new topic from the counts before the sweep: the first topic whose cumulated share passes the uniform number."""
    probs = probabilities(clique_weights(state, n_topics, **priors))
    passed = F.aggregate("probs", F.struct(F.lit(0.0).alias("sum"), F.lit(0).alias("k")), lambda acc, p: F.struct((acc["sum"] + p).alias("sum"), (acc["k"] + (acc["sum"] + p <= F.col("u")).cast("int")).alias("k")), lambda acc: F.least(acc["k"], F.lit(n_topics - 1)))
    return probs.withColumn("u", uniform(seed, sweep, F.col("doc_id"), F.col("g"))).select("doc_id", "g", "words", passed.alias("z"))


def theta(state: DataFrame, n_topics: int, doc_prior: float = 0.5) -> DataFrame:
    """doc_id, k, theta for every document and topic."""
    rows = _vectors(counts(state)[1], "doc_id", n_topics, "n_doc").select("doc_id", F.posexplode("n_doc").alias("k", "cnt"), F.aggregate("n_doc", F.lit(0).cast("long"), lambda a, b: a + b).alias("size"))
    return rows.select("doc_id", "k", ((F.col("cnt") + doc_prior) / (F.col("size") + doc_prior * n_topics)).alias("theta"))


def phi(state: DataFrame, n_topics: int, word_prior: float = 0.01) -> DataFrame:
    """word, k, phi for every word and topic."""
    word_topic, _, topic_total = counts(state)
    vectors = _vectors(word_topic, "word", n_topics, "n_word")
    v, totals = vectors.count(), {r["k"]: r["cnt"] for r in topic_total.collect()}  # n_topics numbers
    total = F.array(*[F.lit(totals.get(k, 0)) for k in range(n_topics)])
    return vectors.select("word", F.posexplode("n_word").alias("k", "cnt")).select("word", "k", ((F.col("cnt") + word_prior) / (F.get(total, F.col("k")) + word_prior * v)).alias("phi"))


def digamma(x: Column) -> Column:
    """The logarithmic derivative of the gamma function for x > 0: six steps of the recurrence, then the asymptotic series."""
    y = x + 6
    below = 1 / x
    for i in range(1, 6):
        below = below + 1 / (x + i)
    return F.log(y) - 1 / (2 * y) - 1 / (12 * y**2) + 1 / (120 * y**4) - 1 / (252 * y**6) + 1 / (240 * y**8) - below


def _doc_prior_step(doc_topic: DataFrame, doc_prior: list[float]) -> DataFrame:
    """k, prior from (doc_id, k, cnt), through histograms of the counts."""
    per_topic = doc_topic.groupBy("k", F.col("cnt").alias("n")).agg(F.count("*").alias("docs"))
    whole = doc_topic.groupBy("doc_id").agg(F.sum("cnt").alias("n")).groupBy("n").agg(F.count("*").alias("docs"))
    prior, mass = F.get(F.array(*map(F.lit, doc_prior)), F.col("k")), F.lit(float(sum(doc_prior)))
    up = per_topic.groupBy("k").agg(F.sum(F.col("docs") * (digamma(F.col("n") + prior) - digamma(prior))).alias("part"))
    down = whole.agg(F.sum(F.col("docs") * (digamma(F.col("n") + mass) - digamma(mass))).alias("below"))
    return up.crossJoin(down).select("k", (prior * F.col("part") / F.col("below")).alias("prior"))  # one row on the right


def prior_step(state: DataFrame, n_topics: int, doc_prior: list[float]) -> DataFrame:
    """k, prior: one fixed-point step of the document priors. Works on the histogram of counts, not on documents."""
    return _doc_prior_step(counts(state)[1], doc_prior)


def _word_prior_step(word_topic: DataFrame, totals: list[int], v: int, word_prior: float) -> float:
    prior = F.lit(word_prior)
    small = word_topic.groupBy(F.col("cnt").alias("n")).agg(F.count("*").alias("cells"))
    parts = small.agg(F.sum(F.col("cells") * (digamma(F.col("n") + prior) - digamma(prior))).alias("up"))
    sizes = word_topic.sparkSession.createDataFrame([(float(t),) for t in totals], "t double")  # n_topics numbers
    below = sizes.agg(F.sum(digamma(F.col("t") + v * word_prior) - digamma(F.lit(v * word_prior))).alias("down"))
    up, down = parts.crossJoin(below).first()
    return word_prior * up / (v * down) if up and down else word_prior


def word_prior_step(state: DataFrame, n_topics: int, word_prior: float) -> float:
    """One fixed-point step of the symmetric word prior; the driver gets two sums and n_topics totals."""
    word_topic, _, topic_total = counts(state)
    return _word_prior_step(word_topic, [r["cnt"] for r in topic_total.collect()], word_topic.select("word").distinct().count(), word_prior)


def log_gamma(x: Column) -> Column:
    @F.pandas_udf("double")
    def run(s: pd.Series) -> pd.Series:
        return s.map(math.lgamma)

    return run(x)


def log_joint(state: DataFrame, n_topics: int, doc_prior: float = 0.5, word_prior: float = 0.01) -> DataFrame:
    """log_joint (one row): log probability of words and topics with both distributions integrated out."""
    word_topic, doc_topic, topic_total = counts(state)
    v = word_topic.select("word").distinct().count()
    lg = math.lgamma
    # sums over histograms: gamma functions are taken once for each distinct count
    sums = []
    for rows, prior in ((doc_topic, doc_prior), (word_topic, word_prior)):
        h = rows.groupBy("cnt").agg(F.count("*").alias("m"))
        sums.append(h.select((F.col("m") * (log_gamma(F.col("cnt") + prior) - lg(prior))).alias("x")))
    sizes = doc_topic.groupBy("doc_id").agg(F.sum("cnt").alias("cnt")).groupBy("cnt").agg(F.count("*").alias("m"))
    sums.append(sizes.select((F.col("m") * (lg(n_topics * doc_prior) - log_gamma(F.col("cnt") + n_topics * doc_prior))).alias("x")))
    sums.append(topic_total.select((lg(v * word_prior) - log_gamma(F.col("cnt") + v * word_prior)).alias("x")))
    whole = sums[0]
    for s in sums[1:]:
        whole = whole.unionByName(s)
    return whole.agg(F.sum("x").alias("log_joint"))


@dataclass
class Model:
    state: DataFrame  # doc_id, g, words, z
    n_topics: int
    doc_prior: np.ndarray
    word_prior: float
    trace: list[dict]


def weights_of(words: np.ndarray, n_doc: np.ndarray, n_word: np.ndarray, n_topic: np.ndarray, doc_prior: np.ndarray, word_prior: float, v: int, repeat_offset: bool = True) -> np.ndarray:
    """Topic weights of a clique given counts without it; n_word is word x topic."""
    long = len(words) > SHORT
    out = np.zeros(len(n_topic)) if long else np.ones(len(n_topic))
    for j, w in enumerate(words):
        seen = int((words[:j] == w).sum()) if repeat_offset and j else 0
        part = (doc_prior + n_doc + j) * (word_prior + n_word[w] + seen) / (v * word_prior + n_topic + j)
        out = out + np.log(part) if long else out * part
    return np.exp(out - out.max()) if long else out


def sweep_rows(docs: list[list[np.ndarray]], topics: list[np.ndarray], n_word: np.ndarray, n_topic: np.ndarray, doc_prior: np.ndarray, word_prior: float, v: int, rng: np.random.Generator, repeat_offset: bool = True) -> None:
    """One sequential sweep over documents, changing topics and counts in place; v is the size of the whole vocabulary."""
    k_all = len(n_topic)
    for cliques, z in zip(docs, topics, strict=True):
        sizes = np.array([len(c) for c in cliques])
        n_doc = np.bincount(z, weights=sizes, minlength=k_all)
        draws = rng.random(len(cliques))
        for i, words in enumerate(cliques):
            old, w = z[i], len(words)
            n_doc[old] -= w
            n_topic[old] -= w
            if w == 1:
                x = words[0]
                n_word[x, old] -= 1
                p = (doc_prior + n_doc) * (word_prior + n_word[x]) / (v * word_prior + n_topic)
            else:
                np.subtract.at(n_word[:, old], words, 1)
                p = weights_of(words, n_doc, n_word, n_topic, doc_prior, word_prior, v, repeat_offset)
            c = np.cumsum(p)
            new = min(int(np.searchsorted(c, draws[i] * c[-1], side="right")), k_all - 1)
            z[i] = new
            n_doc[new] += w
            n_topic[new] += w
            if w == 1:
                n_word[x, new] += 1
            else:
                np.add.at(n_word[:, new], words, 1)


STATE = "block int, doc_id long, gs array<int>, words array<array<int>>, z array<int>"


def sweep_lanes(sizes: np.ndarray, lengths: np.ndarray, tokens: np.ndarray, z: np.ndarray, n_word: np.ndarray, n_topic: np.ndarray, doc_prior: np.ndarray, word_prior: float, v: int, rng: np.random.Generator, repeat_offset: bool = True, lanes: int | None = None) -> None:
    """One sweep over documents given flat: cliques a document, words a clique, word ids, topics (changed in place, as the counts).

    ``lanes`` pieces of like size go side by side (few in a small block): their first cliques are drawn together, then their second ones,
    and so on. A piece is a document, or ``PIECE`` cliques of a longer one. A draw sees the counts, its document's too, without the
    cliques drawn beside it."""
    k_all, v_prior = len(n_topic), v * word_prior
    lanes = lanes or int(min(1024, max(8, len(lengths) // 256)))
    first = np.concatenate([[0], np.cumsum(sizes)])[:-1]
    at = np.concatenate([[0], np.cumsum(lengths)])[:-1]
    parts = -(-sizes // PIECE)
    doc = np.repeat(np.arange(len(sizes)), parts)
    into = (np.arange(len(doc)) - np.repeat(np.cumsum(parts) - parts, parts)) * PIECE
    start, size = first[doc] + into, np.minimum(PIECE, sizes[doc] - into)
    owner = np.repeat(np.arange(len(sizes)), sizes)
    n_doc = np.bincount(owner * k_all + z, weights=lengths, minlength=len(sizes) * k_all).reshape(-1, k_all)
    of_doc, of_word = n_doc.reshape(-1), n_word.reshape(-1)  # views: adding at one index is faster than at two
    order = np.argsort(-size, kind="stable")
    for block in range(0, len(order), lanes):
        group = order[block : block + lanes]
        left = size[group]
        for g in range(int(left[0])):
            live = int(np.searchsorted(-left, -g, side="left"))  # sizes fall, so the live lanes come first
            c, d = start[group[:live]] + g, doc[group[:live]]
            old, w, begin = z[c], lengths[c], at[c]
            np.subtract.at(of_doc, d * k_all + old, w.astype(float))
            n_topic -= np.bincount(old, weights=w, minlength=k_all)
            most, held = int(w.max()), []
            for j in range(most):
                on = slice(None) if j == 0 else np.flatnonzero(w > j)
                x = tokens[begin[on] + j]
                np.subtract.at(of_word, x * k_all + old[on], 1.0)
                held.append((on, x))
            docs = doc_prior + n_doc[d]
            for j, (on, x) in enumerate(held):
                words = n_word[x] + word_prior
                if repeat_offset and j:
                    words += sum((tokens[begin[on] + i] == x) for i in range(j))[:, None]
                part = (docs[on] + j) * words / (v_prior + n_topic + j)
                if most > SHORT:
                    part = np.log(part)
                if j == 0:
                    p = part
                elif most > SHORT:
                    p[on] += part
                else:
                    p[on] *= part
            if most > SHORT:
                p = np.exp(p - p.max(1, keepdims=True))
            sums = np.cumsum(p, axis=1)
            new = np.minimum((sums <= (rng.random(live) * sums[:, -1])[:, None]).sum(1), k_all - 1)
            z[c] = new
            np.add.at(of_doc, d * k_all + new, w.astype(float))
            n_topic += np.bincount(new, weights=w, minlength=k_all)
            for on, x in held:
                np.add.at(of_word, x * k_all + new[on], 1.0)


def _flat(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Cliques a document, words a clique, word ids and topics of a block's rows."""
    words, z = (table.column(c).combine_chunks() for c in ("words", "z"))
    inner = words.flatten()
    numbers = lambda a: a.to_numpy(zero_copy_only=False).astype(np.int64)
    return numbers(pc.list_value_length(words)), numbers(pc.list_value_length(inner)), numbers(inner.flatten()), numbers(z.flatten())


def _sweep(n_topic: np.ndarray, doc_prior: np.ndarray, word_prior: float, v: int, seed: int, sweep: int, inner: int, repeat_offset: bool, exact: bool):
    """The work of one block: its rows and the counts of its words, given as rows of ``counts_of(ids)``."""

    def run(table: pa.Table, counts_of) -> pa.Table:
        table = table.sort_by("doc_id")
        sizes, lengths, tokens, z = _flat(table)
        z = z.copy()
        ids, tokens = np.unique(tokens, return_inverse=True)
        local_word, local_topic = counts_of(ids).astype(np.float64), n_topic.astype(np.float64)
        # the same block recomputed draws the same topics
        rng = np.random.default_rng([seed, sweep, table.column("doc_id")[0].as_py() & 0x7FFFFFFF])
        for _ in range(inner):
            if exact:
                docs = np.split(np.arange(len(lengths)), np.cumsum(sizes)[:-1])
                parts = np.split(tokens, np.cumsum(lengths)[:-1])
                topics_of = [z[d] for d in docs]
                sweep_rows([[parts[i] for i in d] for d in docs], topics_of, local_word, local_topic, doc_prior, word_prior, v, rng, repeat_offset)
                z = np.concatenate(topics_of)
            else:
                sweep_lanes(sizes, lengths, tokens, z, local_word, local_topic, doc_prior, word_prior, v, rng, repeat_offset)
        offsets = pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32))
        return pa.table({**{c: table.column(c) for c in ("block", "doc_id", "gs", "words")}, "z": pa.ListArray.from_arrays(offsets, pa.array(z.astype(np.int32)))})

    return run


def block_of(key: str, labels: list[int], n: int) -> Column:
    """The block of a key, by its hash."""
    at = F.pmod(F.hash(key), F.lit(n))
    return F.get(F.array(*map(F.lit, labels)), at) if labels else at


def block_labels(spark, n: int) -> list[int]:
    """n block numbers that fall on n different partitions of n; none beyond a few thousand, where uneven falls even out."""
    if n > 4096:
        return []
    rows = spark.range(32 * n).select(F.col("id").cast("int").alias("i")).groupBy(F.pmod(F.hash("i"), F.lit(n)).alias("at")).agg(F.min("i").alias("i")).collect()
    found = [r["i"] for r in rows]
    return (found + [i for i in range(32 * n) if i not in set(found)])[:n]


def _tally(k: int):
    """w, k, cnt of a batch of documents' rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            _, lengths, words, z = _flat(pa.Table.from_batches([batch]))
            keys, n = np.unique(words * k + np.repeat(z, lengths), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array((keys // k).astype(np.int32)), pa.array((keys % k).astype(np.int32)), pa.array(n)], ["w", "k", "cnt"])

    return run


def _cells(now: DataFrame, k: int) -> DataFrame:
    """w, k, cnt of the documents' rows, of k topics; added up within batches before rows are made of them."""
    return now.select("words", "z").mapInArrow(_tally(k), "w int, k int, cnt long").groupBy("w", "k").agg(F.sum("cnt").alias("cnt"))


def _dense(rows: DataFrame, key: str, k: int, name: str) -> DataFrame:
    """(key, k, cnt) as (key, array of k counts), for any number of topics."""
    found = rows.groupBy(key).agg(F.map_from_entries(F.collect_list(F.struct("k", "cnt"))).alias("_m"))
    return found.select(key, F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: F.coalesce(F.try_element_at("_m", i), F.lit(0)).cast("double")).alias(name))


def _doc_counts(now: DataFrame) -> DataFrame:
    spread = now.select("doc_id", F.explode(F.arrays_zip("words", "z")).alias("c"))
    return spread.groupBy("doc_id", F.col("c.z").alias("k")).agg(F.sum(F.size("c.words")).alias("cnt"))


def _log_likelihood(tokens: DataFrame, now: DataFrame, cells: DataFrame, totals: np.ndarray, prior: np.ndarray, word_prior: float, places: int) -> tuple[int, float]:
    """Tokens and their log probability, tokens being (doc_id, w, m) with null for a word without a count; ``places`` is the size of the
    vocabulary that the word prior is spread over."""
    k = len(prior)
    p = F.array(*map(F.lit, prior.tolist()))
    size = F.array(*[F.lit(float(t) + word_prior * places) for t in totals])
    none = F.array_repeat(F.lit(0.0), k)
    th = F.zip_with(F.coalesce("n_doc", none), p, lambda a, b: a + b)
    ph = F.zip_with(F.coalesce("n_word", none), size, lambda a, b: (a + word_prior) / b)
    add = lambda x: F.aggregate(x, F.lit(0.0), lambda a, b: a + b)
    joined = tokens.join(_dense(cells, "w", k, "n_word"), "w", "left").join(_dense(_doc_counts(now), "doc_id", k, "n_doc"), "doc_id", "left")
    rows = joined.select("m", th.alias("th"), ph.alias("ph")).select("m", (add(F.zip_with("th", "ph", lambda a, b: a * b)) / add(F.col("th"))).alias("p"))
    n, x = rows.agg(F.sum("m"), F.sum(F.col("m") * F.log("p"))).first()
    return n or 0, x or 0.0


def fit(cliques: DataFrame, n_topics: int | str = 5, sweeps: int = 20, doc_prior: float | None = None, word_prior: float = 0.01, mode: str = "partitioned", partitions: int = 8, seed: int = 7, inner_sweeps: int = 1, optimise_every: int = 0, trace_every: int = 0, repeat_offset: bool = True, k_max: int = 20, concentration: float = 1.0, held: DataFrame | None = None) -> Model:
    """Gibbs sampling over cliques (doc_id, g, words).

    n_topics='auto' starts from k_max topics under a truncated Dirichlet-process prior: after each sweep the document prior's mass
    follows the topics' use by stick breaking, so topics without use fade. mode='exact' is one sequential task, 'partitioned' is
    many blocks (at least ``partitions``, and as many as the corpus needs) with counts merged at every barrier, 'snapshot' is all in
    DataFrame operations. optimise_every=n takes a fixed-point step of the document priors and of the word prior after every n-th
    sweep. trace_every=n notes the training perplexity of every n-th sweep and, with ``held`` (doc_id, words), that of those
    cliques, scored with their documents' topics; words without a count share one more place of the vocabulary.

    snapshot has one fixed prior and one sweep a round, so it raises ValueError where an automatic topic number, prior updates, a
    trace or inner sweeps are asked for. An empty table gives an empty model."""
    from ..functions.text import dense_ids

    auto = n_topics == "auto"
    k = k_max if auto else int(n_topics)
    prior = np.full(k, (50 / k if doc_prior is None else doc_prior) if not auto else concentration / k)
    state = init(cliques, k, seed)
    words = settle(dense_ids(cliques.select(F.explode("words").alias("word")).groupBy("word").agg(F.count("*").alias("cnt")), F.desc("cnt"), F.col("word"), name="word_id"), "words")
    v, n_tokens = (x or 0 for x in words.agg(F.count("*"), F.sum("cnt")).first())
    if mode == "snapshot":
        asked = [n for n, on in (("n_topics='auto'", auto), ("optimise_every", optimise_every), ("trace_every", trace_every), ("inner_sweeps", inner_sweeps != 1)) if on]
        if asked:
            raise ValueError(f"snapshot mode has no {', '.join(asked)}")
        for s in range(1, sweeps + 1):
            before, state = state, settle(snapshot_sweep(state, k, s, seed, doc_prior=float(prior[0]), word_prior=word_prior, repeat_offset=repeat_offset, vocabulary=v), f"sweep-{s}")
            discard(before)
        return Model(state, k, prior, word_prior, [])
    exact = mode == "exact"
    spark = cliques.sparkSession
    blocks = 1 if exact else max(partitions, -(-n_tokens * k // BLOCK_CELLS))
    label = block_of("doc_id", block_labels(spark, blocks), blocks)
    ids = words.select("word", F.col("word_id").cast("int").alias("word_id"))
    long = state.select("doc_id", "g", "z", F.posexplode("words").alias("j", "word")).join(ids, "word")
    coded = long.groupBy("doc_id", "g").agg(F.first("z").alias("z"), F.transform(F.array_sort(F.collect_list(F.struct("j", "word_id"))), lambda x: x["word_id"]).alias("ids"))
    packed = coded.groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("g", "ids", "z"))).alias("c")).select(label.alias("block"), "doc_id", F.transform("c", lambda x: x["g"].cast("int")).alias("gs"), F.transform("c", lambda x: x["ids"]).alias("words"), F.transform("c", lambda x: x["z"]).alias("z"))
    now = settle(packed, "topic-docs")
    ship = v * k <= SHIP_CELLS
    needs = None if ship else settle(now.select("block", F.explode(F.flatten("words")).alias("w")).distinct(), "block-words")
    asked = None
    if trace_every:
        train = settle(now.select("doc_id", F.explode(F.flatten("words")).alias("w")).groupBy("doc_id", "w").agg(F.count("*").alias("m")), "train-tokens")
        if held is not None:
            rows = held.select("doc_id", F.explode("words").alias("word")).join(ids, "word", "left")
            asked = settle(rows.groupBy("doc_id", F.col("word_id").alias("w")).agg(F.count("*").alias("m")), "held-tokens")
    trace = []
    for s in range(sweeps + 1):
        cells = settle(_cells(now, k), f"counts-{s}")
        n_topic = np.zeros(k, np.int64)
        for r in cells.groupBy("k").agg(F.sum("cnt").alias("cnt")).collect():  # n_topics numbers
            n_topic[r["k"]] = r["cnt"]
        if trace_every and s % trace_every == 0:
            n, x = _log_likelihood(train, now, cells, n_topic, prior, word_prior, v)
            note = {"sweep": s, "tokens": n, "perplexity": math.exp(-x / max(1, n))}
            if asked is not None:
                n, x = _log_likelihood(asked, now, cells, n_topic, prior, word_prior, v + 1)
                note |= {"held_tokens": n, "held_perplexity": math.exp(-x / max(1, n))}
            trace.append(note)
        if s == sweeps:
            discard(cells)
            break
        if auto:
            share = np.sort(n_topic)[::-1]
            left = np.concatenate([share[::-1].cumsum()[::-1][1:], [0]])
            stick = (1 + share) / (1 + share + concentration + left)
            sticks = stick * np.concatenate([[1], np.cumprod(1 - stick)[:-1]])
            prior = np.empty(k)
            prior[np.argsort(-n_topic, kind="stable")] = concentration * np.maximum(sticks / sticks.sum(), 1e-6)
        if optimise_every and s and s % optimise_every == 0:
            if not auto:
                for r in _doc_prior_step(_doc_counts(now), prior.tolist()).collect():  # n_topics numbers
                    prior[r["k"]] = max(r["prior"], 1e-6)
            word_prior = max(_word_prior_step(cells, n_topic.tolist(), v, word_prior), 1e-6)
        work = _sweep(n_topic, prior.copy(), word_prior, v, seed, s, inner_sweeps, repeat_offset, exact)
        dealt = now.repartition(blocks, "block").groupBy("block")
        if ship:
            flat = cells.toArrow()
            n_word = np.zeros((v, k), np.int32 if n_tokens < 1 << 31 else np.int64)
            n_word[flat.column("w").to_numpy(), flat.column("k").to_numpy()] = flat.column("cnt").to_numpy()
            sent = spark.sparkContext.broadcast(n_word)
            done = dealt.applyInArrow(_by_broadcast(work, sent), STATE)
        else:
            listed = cells.groupBy("w").agg(F.collect_list("k").alias("ks"), F.collect_list("cnt").alias("cs"))
            slices = needs.join(listed, "w").select("block", "w", "ks", "cs")
            done = dealt.cogroup(slices.repartition(blocks, "block").groupBy("block")).applyInArrow(_by_slices(work, k), STATE)
        before, now = now, settle(done, f"sweep-{s + 1}")
        discard(before)
        discard(cells)
        if ship:
            sent.destroy()
    flat = now.select("doc_id", F.posexplode(F.arrays_zip("gs", "words", "z")).alias("i", "c")).select("doc_id", F.col("c.gs").alias("g"), F.col("c.z").alias("z"), F.posexplode("c.words").alias("j", "word_id"))
    named = flat.join(ids, "word_id").groupBy("doc_id", "g").agg(F.first("z").alias("z"), F.transform(F.array_sort(F.collect_list(F.struct("j", "word"))), lambda x: x["word"]).alias("words"))
    return Model(named.select("doc_id", "g", "words", "z"), k, prior, word_prior, trace)


def _by_broadcast(work, sent):
    def run(table: pa.Table) -> pa.Table:
        return work(table, lambda ids: sent.value[ids])

    return run


def _by_slices(work, k: int):
    def run(table: pa.Table, slices: pa.Table) -> pa.Table:
        def counts_of(ids: np.ndarray) -> np.ndarray:
            out = np.zeros((len(ids), k))
            ks, cs = slices.column("ks").combine_chunks(), slices.column("cs").combine_chunks()
            rows = np.searchsorted(ids, slices.column("w").to_numpy())
            out[np.repeat(rows, pc.list_value_length(ks).to_numpy(zero_copy_only=False)), ks.flatten().to_numpy()] = cs.flatten().to_numpy()
            return out

        return work(table, counts_of)

    return run


def infer(cliques: DataFrame, phis: DataFrame, n_topics: int, sweeps: int = 10, doc_prior: float = 0.5, seed: int = 7) -> DataFrame:
    """doc_id, k, theta of unseen documents under frozen word distributions (word, k, phi). Each document brings the rows of its
    own words only; words without a row are left out."""
    vectors = phis.groupBy("word").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "phi"))), lambda x: x["phi"]).alias("phis"))
    long = cliques.select("doc_id", "g", F.explode("words").alias("word")).join(vectors, "word")
    per = long.groupBy("doc_id", "g").agg(F.collect_list("phis").alias("ps")).groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("g", "ps"))).alias("cs"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, thetas = [], []
            for r in batch.to_pylist():
                rng = np.random.default_rng([seed, r["doc_id"] & 0x7FFFFFFF])
                like = np.array([np.log(np.array(c["ps"])).sum(0) for c in r["cs"]])
                sizes = np.array([len(c["ps"]) for c in r["cs"]])
                z = rng.integers(0, n_topics, len(sizes))
                n = np.bincount(z, weights=sizes, minlength=n_topics)
                mean = np.zeros(n_topics)
                for s in range(sweeps):
                    for i, draw in enumerate(rng.random(len(sizes))):
                        n[z[i]] -= sizes[i]
                        p = like[i] + sizes[i] * np.log(doc_prior + n)
                        c = np.cumsum(np.exp(p - p.max()))
                        z[i] = min(int(np.searchsorted(c, draw * c[-1], side="right")), n_topics - 1)
                        n[z[i]] += sizes[i]
                    mean += n * (s >= sweeps // 2)
                th = mean / max(1, sweeps - sweeps // 2) + doc_prior
                ids.append(r["doc_id"])
                thetas.append((th / th.sum()).tolist())
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(thetas, pa.list_(pa.float64()))], ["doc_id", "theta"])

    return per.mapInArrow(run, "doc_id long, theta array<double>").select("doc_id", F.posexplode("theta").alias("k", "theta"))
