"""Frequent contiguous phrases, level by level over the start positions that are still alive.

A position is a row (uid, at, pid): the frequent phrase ``pid`` of the level starts at token ``at`` of chunk ``uid``. A longer
candidate needs its two overlapping phrases at neighbouring positions, so it is named by that pair of ids: the key of the
counting shuffle is two longs at any length.

Copied passages and runs of one word stay frequent over thousands of lengths. From ``STEPS`` words on the length doubles: two
phrases of n words that overlap or touch, j words apart, name the phrase of n + j words, so one round counts all lengths from
n + 1 to 2n, and the rounds grow with the logarithm of the longest phrase. A round looks at live runs of level n only, so
it counts what the single steps would count.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.io import discard, settle


#: Words up to which phrases grow word by word; from here on the length doubles.
STEPS = 8
#: Texts that the deletions of an edit bound may make of a phrase which is keyed by them.
VARIANTS = 100


@dataclass
class Mined:
    """counts (n, phrase, cnt); spans (uid, at, n, pid); chunks (uid, toks, mult); stats of each level; tokens of the stream."""

    counts: DataFrame
    spans: DataFrame
    chunks: DataFrame
    stats: list[tuple[int, int, int, int]] = field(default_factory=list)
    tokens: int = 0
    min_support: int = 1


def support(value: float, kind: str = "absolute", tokens: int = 0) -> int:
    """A minimum count: the value itself, or value * tokens (linear), at least 2."""
    return max(2, round(value * tokens)) if kind == "linear" else int(value)


def _table(level: DataFrame, label: str) -> DataFrame:
    """A level's frequent phrases with exact unique ids, fixed by writing them."""
    return settle(level.withColumn("pid", F.monotonically_increasing_id()), label)


def frequent_phrases(chunks: DataFrame, min_support: float = 10, max_len: int | None = None, support_kind: str = "absolute", support_by: str = "token", prune_positions: bool = True, prune_docs: bool = True, boundary_rule: str = "exact", for_threshold: float | None = None) -> Mined:
    """Mine chunks (toks[, doc_id]), until no position is left or up to max_len words.

    support_by='document' counts the documents that hold a phrase. prune_positions=False counts every sequence up to max_len and filters after
    (no spans); prune_docs=False goes on to max_len even when no chunk has a live position left. boundary_rule='as_printed' lets a chunk's last
    feasible start at each length go uncounted, as the published listing does when read to the letter. for_threshold=t leaves out
    phrases of two or more words that no merge at threshold t could use (their count must exceed t squared)."""
    by_doc = support_by == "document"
    if by_doc:
        rows = chunks.select("toks", "doc_id").withColumn("uid", F.monotonically_increasing_id()).withColumn("mult", F.lit(1))
    else:
        rows = chunks.groupBy("toks").agg(F.count("*").alias("mult")).withColumn("uid", F.monotonically_increasing_id())
    rows = settle(rows, "mining-chunks")
    tokens = rows.agg(F.sum(F.size("toks") * F.col("mult"))).first()[0] or 0
    least = support(min_support, support_kind, tokens)
    floor = max(least, int(for_threshold**2) + 1) if for_threshold is not None else least
    if not prune_positions:
        longest = max_len or rows.agg(F.max(F.size("toks"))).first()[0] or 1
        return Mined(all_ngrams(chunks, longest).where(F.col("cnt") >= least), None, rows.select("uid", "toks", "mult"), [], tokens, least)
    weight = F.count_distinct("doc_id") if by_doc else F.sum("mult")
    extra = ["doc_id"] if by_doc else ["mult"]

    words = rows.select("uid", *extra, F.posexplode("toks").alias("at", "word"))
    level = _table(words.groupBy("word").agg(weight.alias("cnt")).where(F.col("cnt") >= least).select("cnt", F.col("word").alias("phrase"), F.col("word").alias("last")), "level-1")
    alive = words.join(level.select("pid", F.col("last").alias("word")), "word").select("uid", *extra, "at", "pid")
    out = Mined(level.select(F.lit(1).alias("n"), "phrase", "cnt"), None, rows.select("uid", "toks", "mult"), [], tokens, least)
    spans, n, lines = None, 1, Window.partitionBy("uid").orderBy("at")
    size, alive = level.count(), settle(alive, "alive-1")
    out.stats.append((1, size, size, tokens))
    single = boundary_rule != "exact" or not prune_docs
    while (size or (not prune_docs and max_len)) and (max_len is None or n < max_len):
        if n >= STEPS and not single:
            alive, level, here, listed, stats = _doubled(alive, level, n, min(2 * n, max_len or 2 * n), weight, extra, floor)
            size = sum(x[2] for x in stats if x[0] == 2 * n)
            out.stats += [x for x in stats if x[2]]
            out.counts = out.counts.unionByName(listed)
            spans = here if spans is None else spans.unionByName(here)
            n *= 2
            continue
        follow = alive.withColumn("next_at", F.lead("at").over(lines)).withColumn("next_pid", F.lead("pid").over(lines))
        if boundary_rule == "as_printed":  # the last live start of a chunk is gone before its left neighbour is looked at
            follow = follow.withColumn("_far", F.max("at").over(Window.partitionBy("uid"))).where(F.col("next_at") < F.col("_far"))
        pairs = follow.where(F.col("next_at") == F.col("at") + 1)
        tallied = settle(pairs.groupBy("pid", "next_pid").agg(weight.alias("cnt")), f"candidates-{n + 1}")
        names = level.select(F.col("pid").alias("l"), F.col("phrase").alias("l_phrase")), level.select(F.col("pid").alias("r"), F.col("last").alias("r_last"))
        grown = tallied.where(F.col("cnt") >= floor).join(names[0], F.col("pid") == F.col("l")).join(names[1], F.col("next_pid") == F.col("r"))
        longer = _table(grown.select(F.col("pid").alias("l_id"), F.col("next_pid").alias("r_id"), "cnt", F.concat_ws(" ", "l_phrase", "r_last").alias("phrase"), F.col("r_last").alias("last")), f"level-{n + 1}")
        candidates, size = tallied.count(), longer.count()
        keys = longer.select("l_id", "r_id", F.col("pid").alias("new_pid"), F.col("cnt").alias("new_cnt"))
        moved = pairs.join(keys, (F.col("pid") == F.col("l_id")) & (F.col("next_pid") == F.col("r_id"))).select("uid", *extra, "at", F.col("new_pid").alias("pid"), F.col("new_cnt").alias("cnt"))
        discard(tallied)
        n += 1
        level = longer.select("pid", "cnt", "phrase", "last")
        if not size and prune_docs:
            break
        before, alive = alive, settle(moved, f"alive-{n}")
        if n == 2:  # positions of one word are no spans
            discard(before)
        out.stats.append((n, candidates, size, alive.count()))
        here = alive.select("uid", "at", F.lit(n).alias("n"), "cnt")
        spans = here if spans is None else spans.unionByName(here)
        out.counts = out.counts.unionByName(level.select(F.lit(n).alias("n"), "phrase", "cnt"))
    out.spans = spans if spans is not None else words.select("uid", "at", F.lit(2).alias("n"), F.lit(0).cast("long").alias("cnt")).where("false")
    return out


def _doubled(alive: DataFrame, level: DataFrame, n: int, longest: int, weight: Column, extra: list[str], floor: int) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame, list[tuple[int, int, int, int]]]:
    """All frequent phrases of n + 1 to ``longest`` words, at most 2n, from the live positions of n words: the positions and the level
    table at 2n words, spans and counts of all these lengths, and (length, candidates, frequent, positions) of each."""
    near = Window.partitionBy("uid").orderBy("at").rangeBetween(0, longest - n)
    # the i-th of the positions that follow is i words away where no position between them is dead
    run = F.filter(F.collect_list(F.struct("at", "pid")).over(near), lambda x, i: (i > 0) & (x["at"] == F.col("at") + i))
    pairs = settle(alive.select("uid", *extra, "at", "pid", run.alias("run")).select("uid", *extra, "at", "pid", F.explode("run").alias("x")).select("uid", *extra, "at", "pid", F.col("x.pid").alias("next_pid"), (F.col("x.at") - F.col("at")).alias("j")), f"pairs-{n}")
    tallied = settle(pairs.groupBy("pid", "next_pid", "j").agg(weight.alias("cnt")), f"candidates-{n}")
    names = level.select(F.col("pid").alias("l"), F.col("phrase").alias("l_phrase")), level.select(F.col("pid").alias("r"), F.split("phrase", " ").alias("r_words"))
    # long phrases that overlap are many times larger in memory than in their files, by which the optimizer would broadcast them
    grown = tallied.where(F.col("cnt") >= floor).hint("merge").join(names[0], F.col("pid") == F.col("l")).hint("merge").join(names[1], F.col("next_pid") == F.col("r"))
    phrase = F.concat_ws(" ", F.col("l_phrase"), F.slice("r_words", n - F.col("j") + 1, F.col("j")))
    longer = _table(grown.select(F.col("pid").alias("l_id"), F.col("next_pid").alias("r_id"), F.col("j").alias("step"), "cnt", phrase.alias("phrase")), f"level-{2 * n}")
    keys = longer.select("l_id", "r_id", "step", F.col("pid").alias("new_pid"), F.col("cnt").alias("new_cnt"))
    moved = settle(pairs.join(keys, (F.col("pid") == F.col("l_id")) & (F.col("next_pid") == F.col("r_id")) & (F.col("j") == F.col("step"))).select("uid", *extra, "at", F.col("new_pid").alias("pid"), "j", F.col("new_cnt").alias("cnt")), f"alive-{2 * n}")
    # a row for each length of the round
    asked = {r["j"]: r["c"] for r in tallied.groupBy("j").agg(F.count("*").alias("c")).collect()}
    found = {r["step"]: r["c"] for r in longer.groupBy("step").agg(F.count("*").alias("c")).collect()}
    live = {r["j"]: r["c"] for r in moved.groupBy("j").agg(F.count("*").alias("c")).collect()}
    discard(pairs)
    discard(tallied)
    stats = [(n + j, asked[j], found.get(j, 0), live.get(j, 0)) for j in sorted(asked)]
    top = longer.where(F.col("step") == n).select("pid", "cnt", "phrase")
    return moved.where(F.col("j") == n).select("uid", *extra, "at", "pid"), top, moved.select("uid", "at", (F.col("j") + n).alias("n"), "cnt"), longer.select((F.col("step") + n).alias("n"), "phrase", "cnt"), stats


def all_ngrams(chunks: DataFrame, max_len: int) -> DataFrame:
    """n, phrase, cnt of every contiguous sequence up to max_len: the exhaustive count, without pruning."""
    starts = chunks.select("toks", F.explode(F.sequence(F.lit(1), F.least(F.size("toks"), F.lit(max_len)))).alias("n"))
    grams = starts.select("n", F.explode(F.transform(F.sequence(F.lit(1), F.size("toks") - F.col("n") + 1), lambda i: F.concat_ws(" ", F.slice("toks", i, F.col("n"))))).alias("phrase"))
    return grams.groupBy("n", "phrase").agg(F.count("*").alias("cnt"))


def sketch_filtered(chunks: DataFrame, min_support: int, eps: float = 1e-4, confidence: float = 0.99) -> DataFrame:
    """Bigrams (phrase, cnt) that reach the support, after a count-min sketch has taken out those it proves too rare.
    The sketch has a fixed size and never underestimates, so nothing is lost."""
    import math

    grams = chunks.where(F.size("toks") > 1).select(F.explode(F.transform(F.sequence(F.lit(1), F.size("toks") - 1), lambda i: F.concat_ws(" ", F.slice("toks", i, F.lit(2))))).alias("phrase"))
    width, depth = math.ceil(math.e / eps), math.ceil(math.log(1 / (1 - confidence)))
    cell = lambda seed: F.pmod(F.xxhash64("phrase", F.lit(seed)), F.lit(width)).cast("int")
    hashed = grams
    for seed in range(depth):
        # a counter table of ``width`` rows a seed, so its size is fixed by the parameters
        table = hashed.groupBy(cell(seed).alias("cell")).agg(F.count("*").alias("total")).where(F.col("total") >= min_support).select(F.col("cell").alias(f"c{seed}"))
        grams = grams.join(F.broadcast(table), cell(seed) == F.col(f"c{seed}"), "left_semi")
    return grams.groupBy("phrase").agg(F.count("*").alias("cnt")).where(F.col("cnt") >= min_support)


def order_free(counts: DataFrame) -> DataFrame:
    """Counts of word multisets: phrases with the same words in any order are one."""
    key = F.concat_ws(" ", F.array_sort(F.split("phrase", " ")))
    return counts.groupBy("n", key.alias("words")).agg(F.sum("cnt").alias("cnt"), F.count("*").alias("forms"))


def edit_keys(p: DataFrame, k: int) -> tuple[int, DataFrame]:
    """The length up to which phrases are short for k edits, and n, phrase, key: hashes of the texts that up to k deletions make of the
    short phrases, and of those up to k letters longer, which may have a short one near them."""
    short = next((n for n in range(VARIANTS) if sum(math.comb(n + 1, i) for i in range(k + 1)) > VARIANTS), VARIANTS)
    less = lambda x: F.when(F.length(x) > 0, F.transform(F.sequence(F.lit(1), F.length(x)), lambda i: F.concat(F.substring(x, F.lit(1), i - 1), F.substring(x, i + 1, F.length(x))))).otherwise(F.array(x))
    texts = F.array("phrase")
    for _ in range(k):
        texts = F.array_distinct(F.concat(texts, F.flatten(F.transform(texts, less))))
    rows = p.where(F.length("phrase") <= short + k).select("n", "phrase", F.explode(texts).alias("text"))
    return short, rows.select("n", "phrase", F.xxhash64("n", "text").alias("key"))


def tie_similar(counts: DataFrame, kind: str = "edit", bound: float = 1) -> DataFrame:
    """Pairs (a, b) of similar phrases, a < b. 'edit': Levenshtein distance (in characters) up to bound, a whole number, among phrases
    of as many words; 'jaccard': phrases of two words or more whose word sets are at least bound (over 0) alike; 'stem': different phrases whose
    words have the same stems in order.

    Edit: two phrases within bound edits have a text in common that bound deletions at most make of either. Short phrases, which have up
    to ``VARIANTS`` such texts, are keyed by them; their parts would be a few letters that thousands of words share. Of the bound + 1
    even parts of a longer phrase one at least is untouched by bound edits, and stands in the other phrase at most bound places away;
    the lengths differ by at most bound. Jaccard: two sets that are bound alike share a word among the
    first size - ceil(bound * size) + 1 of each, in one order of all words, rare ones first."""
    p = counts.select("n", "phrase").distinct()
    pair = (F.col("phrase").alias("a"), "b")
    if kind == "edit":
        k = int(bound)
        if k != bound or k < 0:
            raise ValueError("an edit bound is a whole number from 0")
        size = F.length("phrase")
        cut = lambda length, i: F.floor(length * i / (k + 1)).cast("int")
        whole = lambda length, i, at: F.concat_ws("|", length, i, F.substring(F.col("phrase"), at + 1, cut(length, i + 1) - cut(length, i)))
        short, keyed = edit_keys(p, k)
        near = keyed.select(F.col("n").alias("m"), F.col("phrase").alias("b"), F.col("key").alias("key_b"))
        close = keyed.hint("merge").join(near, (F.col("key") == F.col("key_b")) & (F.col("n") == F.col("m")) & (F.col("phrase") < F.col("b"))).where(F.levenshtein("phrase", "b", k) >= 0).select(*pair)
        p = p.where(size > short)
        own = p.select("n", "phrase", F.explode(F.array(*[whole(size, F.lit(i), cut(size, F.lit(i))) for i in range(k + 1)])).alias("key"))
        # the parts as a phrase of each length within bound would have them, at each place within bound
        shifts = [(F.lit(i), size + d, s) for i in range(k + 1) for d in range(-k, k + 1) for s in range(-k, k + 1)]
        there = F.array_distinct(F.array(*[F.when((length >= 0) & (cut(length, i) + s >= 0) & (cut(length, i + 1) + s <= size), whole(length, i, cut(length, i) + s)) for i, length, s in shifts]))
        other = p.select(F.col("n").alias("m"), F.col("phrase").alias("b"), F.explode(F.filter(there, lambda x: x.isNotNull())).alias("key_b"))
        # the size the optimizer sees is that of the phrases, which have some 75 keys each: without the hint it broadcasts them all
        met = own.hint("merge").join(other, (F.col("key") == F.col("key_b")) & (F.col("n") == F.col("m")) & (F.col("phrase") != F.col("b"))).where(F.levenshtein("phrase", "b", k) >= 0)
        return close.unionByName(met.select(F.least("phrase", "b").alias("a"), F.greatest("phrase", "b").alias("b"))).distinct()
    if kind == "stem":
        from ..functions.stem import stem_phrase

        named = p.select("phrase", stem_phrase(F.col("phrase")).alias("stems"))
        other = named.select(F.col("phrase").alias("b"), F.col("stems").alias("stems_b"))
        return named.join(other, (F.col("stems") == F.col("stems_b")) & (F.col("phrase") < F.col("b"))).select(*pair)
    if not 0 < bound <= 1:
        raise ValueError("a share of common words is over 0 and at most 1")
    sets = p.where("n > 1").select("phrase", F.array_distinct(F.split("phrase", " ")).alias("ws"))
    words = sets.select("phrase", F.explode("ws").alias("w"))
    often = words.groupBy("w").agg(F.count("*").alias("c"))
    ranked = words.join(often, "w").groupBy("phrase").agg(F.transform(F.array_sort(F.collect_list(F.struct("c", "w"))), lambda x: x["w"]).alias("ws"))
    # the share is taken in whole numbers of a millionth, so that no rounding shortens the prefix
    least = F.ceil((F.size("ws") * F.lit(round(bound * 1_000_000)) - 1) / 1_000_000)
    rows = ranked.select("phrase", "ws", F.explode(F.slice("ws", 1, F.greatest(F.lit(1), F.size("ws") - least + 1).cast("int"))).alias("w"))
    other = rows.select(F.col("phrase").alias("b"), F.col("ws").alias("ws_b"), F.col("w").alias("w_b"))
    alike = F.size(F.array_intersect("ws", "ws_b")) / F.size(F.array_union("ws", "ws_b"))
    return rows.join(other, (F.col("w") == F.col("w_b")) & (F.col("phrase") < F.col("b"))).where(alike >= bound).select(*pair).distinct()


def ngrams_of(toks: Column, n: int) -> Column:
    """Array of the n-grams of a token array."""
    return F.when(F.size(toks) >= n, F.transform(F.sequence(F.lit(1), F.size(toks) - n + 1), lambda i: F.concat_ws(" ", F.slice(toks, i, n)))).otherwise(F.array().cast("array<string>"))
