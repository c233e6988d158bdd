"""The compared methods, each rebuilt on the same chunks, cliques and rankings."""

from __future__ import annotations

import hashlib
import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.io import discard, settle
from . import packed, topics

#: Successors that a permutation deals at once, those that a task deals in all, and tokens that a block of the bigram switch holds.
DEAL, DEAL_TASK, SWITCH_TOKENS = 8_000_000, 2_000_000, 200_000
#: Tokens that a block of the Pitman-Yor model holds.
SEATED_TOKENS = 400_000
#: Pieces up to which a loop is faster than arrays.
FEW = 8
#: Tokens over which a document is drawn in pieces of whole chunks, and documents whose counts are taken at once.
PIECE, TALLIED = 512, 1024


def lda(chunks: DataFrame, **options) -> topics.Model:
    """Word-level topic model: the clique model's own code over one-word cliques."""
    return topics.fit(topics.singletons(chunks), **options)


def tokens_with_topics(chunks: DataFrame, model: topics.Model) -> DataFrame:
    """doc_id, chunk_no, pos, word, z of a word-level model."""
    order = Window.partitionBy("doc_id").orderBy("chunk_no", "pos")
    rows = chunks.select("doc_id", "chunk_no", F.posexplode("toks").alias("pos", "word")).withColumn("g", F.row_number().over(order) - 1)
    return rows.join(model.state.select("doc_id", "g", "z"), ["doc_id", "g"]).select("doc_id", "chunk_no", "pos", "word", "z")


def _gain(n_vw: Column, n_v: Column, p_w: Column) -> Column:
    pi = n_vw / n_v
    rest = F.when(n_vw < n_v, (n_v - n_vw) * F.log((1 - pi) / (1 - p_w))).otherwise(0.0)
    return n_vw * F.log(pi / p_w) + rest


#: A topic's deck: how many v have n slots (ns, nc), how many w have m slots among these and n_w in all (ms, ws, mc), all slots.
DECK = "k int, perm int, part int, ns array<long>, nc array<long>, ms array<long>, ws array<long>, mc array<long>, total long"


def drawn(rng: np.random.Generator, colours: np.ndarray, size: int) -> np.ndarray:
    """How many of each colour are among ``size`` slots drawn without replacement: each slot is taken by chance, then as many are put
    back or taken as are over or wanting, so that all sets of that size are equally likely, for any number of slots."""
    taken = rng.binomial(colours, size / colours.sum())
    off = size - int(taken.sum())
    pool = colours - taken if off > 0 else taken
    at = rng.choice(int(pool.sum()), abs(off), replace=False)
    return taken + (1 if off > 0 else -1) * np.bincount(np.searchsorted(np.cumsum(pool), at, side="right"), minlength=len(colours))


def _deck_parts(seed: int):
    """A permuted deck cut into parts of about ``DEAL`` slots between the v: each part draws its successors from those that are left.
    A v over that size is a part of its own."""

    def run(key: tuple[pa.Scalar, ...], deck: pa.Table) -> pa.Table:
        row = deck.to_pylist()[0]
        n, m, w = np.repeat(row["ns"], row["nc"]), np.repeat(row["ms"], row["mc"]), np.repeat(row["ws"], row["mc"])
        rng, out = np.random.default_rng([seed, row["k"], row["perm"]]), []
        ends = np.cumsum(n)
        begin = 0
        while begin < len(n):
            done = ends[begin] - n[begin]
            end = max(begin + 1, int(np.searchsorted(ends, done + DEAL, side="right")))
            size = int(ends[end - 1] - done)
            taken = m if end == len(n) else drawn(rng, m, size)
            m = m - taken
            some = taken > 0
            sides = np.unique(np.stack([taken[some], w[some]]), axis=1, return_counts=True)
            ns, nc = np.unique(n[begin:end], return_counts=True)
            out.append(row | {"part": len(out), "ns": ns, "nc": nc, "ms": sides[0][0], "ws": sides[0][1], "mc": sides[1]})
            begin = end
        return pa.Table.from_pylist([{c: x.tolist() if isinstance(x, np.ndarray) else x for c, x in r.items()} for r in out], deck.schema)

    return run


def _deal(seed: int):
    """k, perm, peak: the largest gain once a part's successors are dealt to its v."""

    def run(key: tuple[pa.Scalar, ...], deck: pa.Table) -> pa.Table:
        row = deck.to_pylist()[0]
        n, m, p = np.repeat(row["ns"], row["nc"]), np.repeat(row["ms"], row["mc"]), np.repeat(row["ws"], row["mc"]) / row["total"]
        if len(n) == 1:
            v, w, both = np.zeros(len(m), np.int64), np.arange(len(m)), m
        else:
            slots = np.repeat(np.arange(len(m), dtype=np.int64), m)
            np.random.default_rng([seed, row["k"], row["perm"], 1 + row["part"]]).shuffle(slots)
            slots += np.repeat(np.arange(len(n), dtype=np.int64), n) * len(m)
            slots.sort()
            first = np.flatnonzero(np.concatenate([[True], slots[1:] != slots[:-1]]))
            v, w = np.divmod(slots[first], len(m))
            both = np.diff(np.append(first, len(slots)))
        n, p = n[v], p[w]
        with np.errstate(all="ignore"):
            rest = np.where(both < n, (n - both) * np.log((1 - both / n) / (1 - p)), 0.0)
            peak = float((both * np.log(both / n / p) + rest).max())
        return pa.table({"k": pa.array([row["k"]], pa.int32()), "perm": pa.array([row["perm"]], pa.int32()), "peak": [peak]})

    return run


def _significant(pairs: DataFrame, p_value: float, n_perm: int, seed: int, min_count: int) -> DataFrame:
    """posthoc_round of the counts (k, v, w, n) of all neighbours. Permutations go by the counts of v and of w alone, as histograms,
    so what is dealt is made in the tasks and no slot is written."""
    firsts = settle(pairs.groupBy("k", "v").agg(F.sum("n").alias("n_v"), F.max("n").alias("most")), "posthoc-firsts")
    heads = firsts.where(F.col("most") >= min_count)
    totals = firsts.groupBy("k").agg(F.sum("n_v").alias("total"))
    # successors in all, and those of heads
    known = pairs.join(heads.select("k", "v", F.lit(1).alias("head")), ["k", "v"], "left")
    share = settle(known.groupBy("k", "w").agg(F.sum("n").alias("n_w"), F.coalesce(F.sum(F.when(F.col("head") == 1, F.col("n"))), F.lit(0)).alias("m")).join(totals, "k"), "posthoc-shares")
    left = heads.groupBy("k", F.col("n_v").alias("n")).agg(F.count("*").alias("c")).groupBy("k").agg(F.sort_array(F.collect_list(F.struct("n", "c")), False).alias("l"))
    right = share.where("m > 0").groupBy("k", "m", "n_w", "total").agg(F.count("*").alias("c")).groupBy("k", "total").agg(F.sort_array(F.collect_list(F.struct("m", "n_w", "c")), False).alias("r"))
    lists = [F.col("l.n").alias("ns"), F.col("l.c").alias("nc"), F.col("r.m").alias("ms"), F.col("r.n_w").alias("ws"), F.col("r.c").alias("mc")]
    decks = settle(left.join(right, "k").select(F.col("k").cast("int").alias("k"), F.explode(F.sequence(F.lit(1), F.lit(n_perm))).alias("perm"), F.lit(0).alias("part"), *lists, "total"), "posthoc-decks")
    slots = F.aggregate(F.zip_with("ns", "nc", lambda n, c: n * c), F.lit(0).cast("long"), lambda a, x: a + x)
    most, every = (x or 0 for x in decks.select(slots.alias("slots")).agg(F.max("slots"), F.sum("slots")).first())
    tasks = min(4096, 8 + every // DEAL_TASK)
    dealt = settle(decks.repartition(tasks, "k", "perm").groupBy("k", "perm").applyInArrow(_deck_parts(seed), DECK), "posthoc-parts") if most > DEAL else decks
    peaks = dealt.repartition(tasks, "k", "perm", "part").groupBy("k", "perm", "part").applyInArrow(_deal(seed), "k int, perm int, peak double").groupBy("k", "perm").agg(F.max("peak").alias("peak"))
    bars = settle(peaks.groupBy("k").agg(F.percentile("peak", F.lit(1 - p_value)).alias("bar")), "posthoc-bars")
    real = pairs.where(F.col("n") >= min_count).join(heads.select("k", "v", "n_v"), ["k", "v"]).join(share.select("k", "w", (F.col("n_w") / F.col("total")).alias("p_w")), ["k", "w"])
    found = settle(real.withColumn("gain", _gain(F.col("n"), F.col("n_v"), F.col("p_w"))).join(bars, "k").where("gain > bar").select("k", "v", "w", "n", "gain", "bar"), "posthoc-found")
    for table in (firsts, share, decks, dealt, bars):
        discard(table)
    return found


def posthoc_round(tokens: DataFrame, p_value: float = 0.05, n_perm: int = 20, seed: int = 7, min_count: int = 5) -> DataFrame:
    """k, v, w, n, gain, bar: pairs of one round whose gain over the back-off law beats the (1 - p) quantile of the largest gains of
    permutations, in which the successors of all v in a topic are dealt anew. Above ``DEAL`` slots a topic's permutation is dealt in parts
    of about that size, whose shares of each successor are drawn first, so that every permutation is as likely as in one piece."""
    return _significant(settle(packed.adjacent_pairs(packed.pack(tokens)), "posthoc-pairs"), p_value, n_perm, seed, min_count)


def posthoc_merge(tokens: DataFrame, p_value: float = 0.05, n_perm: int = 20, max_rounds: int | None = None, seed: int = 7, min_count: int = 5) -> DataFrame:
    """Tokens after recursive merging of significant same-topic neighbours: doc_id, chunk_no, pos, word (a phrase), z. Without max_rounds
    it goes on until no pair is significant; a round joins two units at least, so it ends."""
    return packed.rows(posthoc_docs(packed.pack(tokens), p_value, n_perm, max_rounds, seed, min_count)).select("doc_id", "chunk_no", "pos", "word", "z")


def posthoc_docs(docs: DataFrame, p_value: float = 0.05, n_perm: int = 20, max_rounds: int | None = None, seed: int = 7, min_count: int = 5) -> DataFrame:
    """The same on rows of documents (packed.DOCS), which come back with a merged phrase in the place of its words."""
    given, blocks = docs, max(1, docs.select("block").distinct().count())
    for step in itertools.count() if max_rounds is None else range(max_rounds):
        counted = settle(packed.block_pairs(docs), f"posthoc-counted-{step}")
        pairs = settle(counted.groupBy("k", "v", "w").agg(F.sum("n").alias("n")), f"posthoc-pairs-{step}")
        found = _significant(pairs, p_value, n_perm, seed + step, min_count)
        discard(pairs)
        if found.isEmpty():
            discard(counted)
            break
        keys = counted.join(found.select("k", "v", "w"), ["k", "v", "w"]).select("block", "k", "v", "w").distinct()
        sides = docs.repartition(blocks, "block").groupBy("block"), keys.repartition(blocks, "block").groupBy("block")
        before, docs = docs, settle(sides[0].cogroup(sides[1]).applyInArrow(packed.merged, packed.DOCS), f"posthoc-{step}")
        discard(counted)
        if before is not given:
            discard(before)
    return docs


SWITCH = "block int, doc_id long, ids array<int>, inner array<int>, z array<int>, x array<int>"


def _switch_start(n_topics: int, seed: int):
    """Topics and flags before the first sweep, by document. Half of the neighbours start glued: from none at all, a pair would wait
    long for its first count."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            z, x = [], []
            for doc, inner in zip(batch.column(1).to_pylist(), batch.column(3).to_pylist(), strict=True):
                rng = np.random.default_rng([seed, doc & 0x7FFFFFFF])
                z.append(rng.integers(0, n_topics, len(inner)).tolist())
                x.append((rng.integers(0, 2, len(inner)) * np.array(inner, np.int64)).tolist())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(z, pa.list_(pa.int32())), pa.array(x, pa.list_(pa.int32()))], ["block", "doc_id", "ids", "inner", "z", "x"])

    return run


def _switch_tally(v: int):
    """Counts of the documents of a task, by kind: 0 free word (topic, word), 1 glued word (topic, word before, word), 2 glued words
    behind (topic, word before), 3 flags (topic before, word before, flag)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for begin in range(0, whole.num_rows, TALLIED):
                ids, inner, z, x = (_numbers(c.flatten()) for c in whole.slice(begin, TALLIED).columns)
                pw, pz = np.roll(ids, 1), np.roll(z, 1)  # read where inner is 1 only, so never over a document's start
                on, off, tied = x == 1, x == 0, inner == 1
                for kind, a, b, c in ((0, z[off], ids[off], 0), (1, z[on], pw[on], ids[on]), (2, z[on], pw[on], 0), (3, pz[tied], pw[tied], x[tied])):
                    keys, n = np.unique((a * v + b) * v + c, return_counts=True)
                    rest, c = np.divmod(keys, v)
                    a, b = np.divmod(rest, v)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), kind), pa.int32()), pa.array(a, pa.int32()), pa.array(b, pa.int32()), pa.array(c, pa.int32()), pa.array(n, pa.int64())], ["kind", "a", "b", "c", "n"])

    return run


def _numbers(a: pa.Array) -> np.ndarray:
    return a.to_numpy(zero_copy_only=False).astype(np.int64)


def _switch_slices(now: DataFrame, v: int) -> DataFrame:
    """kind, a, b, c, n: the counts of all documents in one pass over them (kinds as above). With v = 1 a flag would not fit its place
    of the key, so there are 2 at least."""
    return now.select("ids", "inner", "z", "x").mapInArrow(_switch_tally(max(2, v)), "kind int, a int, b int, c int, n long").groupBy("kind", "a", "b", "c").agg(F.sum("n").alias("n"))


def switch_lanes(sizes: np.ndarray) -> int:
    """Pieces that a block draws side by side: few in a small block, so that hardly any draw misses the one beside it."""
    return int(min(1024, max(8, sizes.sum() // 256)))


def _pieces(sizes: np.ndarray, inner: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First token, tokens and document of the pieces that go side by side: documents, those over PIECE tokens cut at chunk starts."""
    first = np.concatenate([[0], np.cumsum(sizes)])[:-1]
    doc = np.repeat(np.arange(len(sizes)), sizes)
    heads = np.flatnonzero(inner == 0)
    part = (heads - first[doc[heads]]) // PIECE
    fresh = np.ones(len(heads), bool)
    fresh[1:] = (doc[heads[1:]] != doc[heads[:-1]]) | (part[1:] != part[:-1])
    start = heads[fresh]
    return start, np.diff(np.append(start, len(inner))), doc[start]


def _switch_sweep(n_topics: int, nk: np.ndarray, doc_prior: float, beta: float, gamma: float, delta: float, v: int, seed: int, sweep: int):
    """One sweep over a block's documents, from the counts of all documents at its start and the block's own changes since. Pieces of
    like size go side by side: their first words are drawn together, then their second ones; a draw sees the counts without the words
    drawn beside it."""

    def run(key: tuple[pa.Scalar, ...], docs: pa.Table, slices: pa.Table) -> pa.Table:
        rng = np.random.default_rng([seed, sweep, key[0].as_py()])
        docs = docs.sort_by("doc_id").combine_chunks()
        column = lambda c: docs.column(c).combine_chunks()
        sizes = _numbers(pc.list_value_length(column("ids")))
        ids, inner, z, x = (_numbers(column(c).flatten()) for c in ("ids", "inner", "z", "x"))
        z, x, total = z.copy(), x.copy(), nk.copy()
        words, w = np.unique(ids, return_inverse=True)
        before, tied = np.roll(w, 1), inner == 1
        pairs, at_pair = np.unique(before[tied] * len(words) + w[tied], return_inverse=True)
        pair = np.zeros(len(w), np.int64)
        pair[tied] = at_pair
        free, behind, follow, glued = np.zeros((len(words), n_topics), np.int32), np.zeros((len(words), n_topics), np.int32), np.zeros((len(words), n_topics, 2), np.int32), np.zeros((len(pairs), n_topics), np.int32)
        kind, a, b, c, n = (_numbers(slices.column(x)) for x in ("kind", "a", "b", "c", "n"))
        b = np.searchsorted(words, b)
        for i, held in ((0, free), (2, behind)):
            on = kind == i
            held[b[on], a[on]] = n[on]
        on = kind == 3
        follow[b[on], a[on], c[on]] = n[on]
        on = kind == 1
        glued[np.searchsorted(pairs, b[on] * len(words) + np.searchsorted(words, c[on])), a[on]] = n[on]
        n_doc = np.bincount(np.repeat(np.arange(len(sizes)), sizes) * n_topics + z, minlength=len(sizes) * n_topics).reshape(len(sizes), n_topics)
        start, length, doc = _pieces(sizes, inner)
        # numbered through, as adding at one index is several times faster than at two
        of_doc, of_free, of_behind, of_follow, of_glued = (m.ravel() for m in (n_doc, free, behind, follow, glued))
        k = n_topics
        order, lanes = np.argsort(-length, kind="stable"), switch_lanes(sizes)
        for begin in range(0, len(order), lanes):
            group = order[begin : begin + lanes]
            left = length[group]
            for i in range(int(left[0])):
                live = int(np.searchsorted(-left, -i, side="left"))  # lengths fall, so the live pieces come first
                c, d = start[group[:live]] + i, doc[group[:live]]
                old, flag, word, t = z[c], x[c], w[c], np.flatnonzero(tied[c])
                g, f = np.flatnonzero(flag == 1), np.flatnonzero(flag == 0)
                pw, pz, two = before[c[t]], z[c[t] - 1], pair[c[t]]
                side = (pw * k + pz) * 2
                np.subtract.at(of_doc, d * k + old, 1)
                np.subtract.at(of_follow, side + flag[t], 1)
                np.subtract.at(of_glued, pair[c[g]] * k + old[g], 1)
                np.subtract.at(of_behind, before[c[g]] * k + old[g], 1)
                np.subtract.at(of_free, word[f] * k + old[f], 1)
                total -= np.bincount(old[f], minlength=k)
                th = doc_prior + n_doc[d]
                p = np.zeros((live, 2 * k))
                p[:, :k] = th * (beta + free[word]) / (v * beta + total)
                s = gamma + follow[pw, pz]
                p[t, :k] *= s[:, :1]
                p[t, k:] = s[:, 1:] * th[t] * (delta + glued[two]) / (v * delta + behind[pw])
                sums = np.cumsum(p, axis=1)
                # a word at a chunk's start has no flag to draw
                pick = np.minimum((sums <= (rng.random(live) * sums[:, -1])[:, None]).sum(1), np.where(tied[c], 2, 1) * k - 1)
                flag, new = np.divmod(pick, k)
                z[c], x[c] = new, flag
                g, f = np.flatnonzero(flag == 1), np.flatnonzero(flag == 0)
                np.add.at(of_doc, d * k + new, 1)
                np.add.at(of_follow, side + flag[t], 1)
                np.add.at(of_glued, pair[c[g]] * k + new[g], 1)
                np.add.at(of_behind, before[c[g]] * k + new[g], 1)
                np.add.at(of_free, word[f] * k + new[f], 1)
                total += np.bincount(new[f], minlength=k)
                # the next word's flag is counted under this topic
                m = np.flatnonzero((old != new) & (i + 1 < left[:live]))
                m = m[tied[c[m] + 1]]
                f = x[c[m] + 1]
                np.subtract.at(of_follow, (word[m] * k + old[m]) * 2 + f, 1)
                np.add.at(of_follow, (word[m] * k + new[m]) * 2 + f, 1)
        offsets = pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32))
        listed = lambda a: pa.ListArray.from_arrays(offsets, pa.array(a.astype(np.int32)))
        return pa.table({**{c: docs.column(c) for c in ("block", "doc_id", "ids", "inner")}, "z": listed(z), "x": listed(x)})

    return run


def _coded(chunks: DataFrame) -> tuple[DataFrame, DataFrame, int]:
    """docs (doc_id, ids, inner, toks), words (word, word_id), size of the vocabulary; inner is 0 at a chunk's first token."""
    from ..functions.text import vocabulary

    words = vocabulary(chunks)
    long = chunks.select("doc_id", "chunk_no", F.posexplode("toks").alias("pos", "word")).join(words.select("word", "word_id"), "word")
    item = F.struct("chunk_no", "pos", F.col("word_id").cast("int").alias("id"), "word")
    docs = long.groupBy("doc_id").agg(F.array_sort(F.collect_list(item)).alias("t")).select("doc_id", F.transform("t", lambda t: t["id"]).alias("ids"), F.transform("t", lambda t: (t["pos"] > 0).cast("int")).alias("inner"), F.transform("t", lambda t: t["word"]).alias("toks"))
    return settle(docs, "coded-docs"), words, words.count()


def glued_runs(tokens: DataFrame) -> DataFrame:
    """doc_id, run, phrase, len, z: maximal runs of a head and the tokens glued to their left neighbour (x = 1), by gaps and
    islands over (doc_id, i, word, x, z); the topic is that of the last word."""
    runs = tokens.withColumn("run", F.sum((F.col("x") == 0).cast("int")).over(Window.partitionBy("doc_id").orderBy("i")))
    return runs.groupBy("doc_id", "run").agg(F.array_sort(F.collect_list(F.struct("i", "word", "z"))).alias("t")).select("doc_id", "run", F.concat_ws(" ", F.transform("t", lambda t: t["word"])).alias("phrase"), F.size("t").alias("len"), F.element_at("t", -1)["z"].alias("z"))


def bigram_switch(chunks: DataFrame, n_topics: int = 5, sweeps: int = 10, doc_prior: float = 0.5, beta: float = 0.01, gamma: float = 0.1, delta: float = 0.01, partitions: int = 8, seed: int = 7) -> DataFrame:
    """Phrases (doc_id, run, phrase, len, z) of a model in which a word may be glued to the one before it and then comes from a
    distribution of its own for that topic and word. Blocks of documents (at least ``partitions``, and one for each SWITCH_TOKENS
    tokens) sweep from the same counts, which are taken anew from all of them after each sweep; a block is sent the counts of
    its own words and neighbours only."""
    docs, words, v = _coded(chunks)
    tokens = words.agg(F.sum("cnt")).first()[0] or 0
    blocks = max(partitions, -(-tokens // SWITCH_TOKENS))
    block = topics.block_of("doc_id", topics.block_labels(chunks.sparkSession, blocks), blocks)
    now = settle(docs.select(block.alias("block"), "doc_id", "ids", "inner").mapInArrow(_switch_start(n_topics, seed), SWITCH), "switch")
    near = now.select("block", F.explode(F.transform("ids", lambda w, i: F.struct(w.alias("w"), F.get("ids", i - 1).alias("pw"), F.get("inner", i).alias("inner")))).alias("t"))
    needs = settle(near.select("block", F.col("t.w").alias("w")).distinct(), "switch-words")
    pairs = settle(near.where("t.inner = 1").select("block", "t.pw", "t.w").distinct(), "switch-pairs")
    for s in range(sweeps):
        rows = settle(_switch_slices(now, v), "switch-counts")
        nk = np.zeros(n_topics)
        for r in rows.where("kind = 0").groupBy("a").agg(F.sum("n").alias("n")).collect():  # n_topics numbers
            nk[r["a"]] = r["n"]
        single = rows.where("kind <> 1").join(needs, F.col("b") == F.col("w")).select("block", "kind", "a", "b", "c", "n")
        both = rows.where("kind = 1").join(pairs, (F.col("b") == F.col("pw")) & (F.col("c") == F.col("w"))).select("block", "kind", "a", "b", "c", "n")
        sides = now.repartition(blocks, "block").groupBy("block"), single.unionByName(both).repartition(blocks, "block").groupBy("block")
        before, now = now, settle(sides[0].cogroup(sides[1]).applyInArrow(_switch_sweep(n_topics, nk, doc_prior, beta, gamma, delta, v, seed, s), SWITCH), "switch")
        discard(before)
        discard(rows)
    both = docs.select("doc_id", "toks").join(now.select("doc_id", "z", "x"), "doc_id")
    return glued_runs(both.select("doc_id", F.posexplode(F.arrays_zip("toks", "z", "x")).alias("i", "t")).select("doc_id", "i", F.col("t.toks").alias("word"), F.col("t.z").alias("z"), F.col("t.x").alias("x")))


def itemset_keyphrases(tokens: DataFrame, min_support: int = 10, max_size: int = 2, purity_weight: float = 0.5, complete: float = 0.1, largest_set: int | None = None) -> DataFrame:
    """k, items, f, coverage, purity, concordance, completeness, score: frequent word sets among the words of one topic in one
    document. Only words that are frequent in their topic are paired. With largest_set, a transaction over so many words is an error
    before the number of its sets explodes; without, all are worked through."""
    baskets = tokens.select("doc_id", F.col("z").alias("k"), "word").distinct()
    worst = (baskets.groupBy("doc_id", "k").count().agg(F.max("count")).first()[0] or 0) if largest_set is not None else 0
    if largest_set is not None and worst > largest_set:
        raise ValueError(f"a transaction has {worst} words, over {largest_set}")
    n_k = baskets.select("doc_id", "k").distinct().groupBy("k").agg(F.count("*").alias("n_k"))
    ones = baskets.groupBy("k", "word").agg(F.count("*").alias("f")).where(F.col("f") >= min_support)
    level = ones.select("k", F.array("word").alias("items"), "f")
    kept = baskets.join(ones.select("k", "word"), ["k", "word"])
    sets, held = level, kept.select("doc_id", "k", F.array("word").alias("items"))
    for _ in range(2, max_size + 1):
        grown = held.join(kept, ["doc_id", "k"]).where(F.col("word") > F.element_at("items", -1)).select("doc_id", "k", F.concat("items", F.array("word")).alias("items"))
        level = settle(grown.groupBy("k", "items").agg(F.count("*").alias("f")).where(F.col("f") >= min_support), "itemsets")
        held = grown.join(level.select("k", "items"), ["k", "items"], "left_semi")
        sets = sets.unionByName(level)
    sets = settle(sets, "all-itemsets")
    words = ones.select("k", "word", F.col("f").alias("f_w"))
    single = sets.select("k", "items", "f", F.explode("items").alias("word")).join(words, ["k", "word"]).join(n_k, "k")
    rated = single.groupBy("k", "items").agg(F.first("f").alias("f"), F.first("n_k").alias("n_k"), F.sum(F.log(F.col("f_w") / F.col("n_k"))).alias("logp"))
    # purity against the largest pooled share with another topic
    share = rated.withColumn("share", F.col("f") / F.col("n_k"))
    other = share.select("items", F.col("k").alias("k2"), F.col("f").alias("f2"), F.col("n_k").alias("n2"))
    pooled = share.join(other, "items").where("k <> k2").groupBy("k", "items").agg(F.max((F.col("f") + F.col("f2")) / (F.col("n_k") + F.col("n2"))).alias("pool"))
    supers = sets.where(F.size("items") > 1).select("k", "items", "f", F.explode(F.sequence(F.lit(0), F.size("items") - 1)).alias("i")).select("k", F.filter("items", lambda x, j: j != F.col("i")).alias("items"), F.col("f").alias("f_up")).groupBy("k", "items").agg(F.max("f_up").alias("f_up"))
    full = share.join(pooled, ["k", "items"], "left").join(supers, ["k", "items"], "left")
    mean = F.exp("logp") * F.col("n_k")
    out = full.select("k", "items", "f", F.col("share").alias("coverage"), F.log(F.col("share") / F.coalesce("pool", F.col("share"))).alias("purity"), ((F.col("f") - mean) / F.sqrt("f")).alias("concordance"), (1 - F.coalesce("f_up", F.lit(0)) / F.col("f")).alias("completeness"))
    return out.where(F.col("completeness") >= complete).withColumn("score", F.col("coverage") * (purity_weight * F.col("purity") + (1 - purity_weight) * F.col("concordance")))


def itemsets(baskets: DataFrame, min_support: float, max_size: int = 2) -> DataFrame:
    """items array<string>, freq: general frequent sets of baskets (items) by parallel FP-growth, at most max_size items."""
    from pyspark.ml.fpm import FPGrowth

    return FPGrowth(itemsCol="items", minSupport=min_support).fit(baskets).freqItemsets.where(F.size("items") <= max_size)


def _pitman_yor_start(n_topics: int, seed: int):
    """Each word a phrase of its own with a topic by chance, by document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = [len(ids) for ids in batch.column(2)]
            z = [np.random.default_rng([seed, (doc or 0) & 0x7FFFFFFF]).integers(0, n_topics, n, np.int32) for doc, n in zip(batch.column(1).to_pylist(), sizes, strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(z, pa.list_(pa.int32())), pa.array([np.zeros(n, np.int32) for n in sizes], pa.list_(pa.int32()))], ["block", "doc_id", "ids", "inner", "z", "x"])

    return run


#: n customers of word w in a context of depth words (ctx: its hash, empty without words); a and b are its first two words, last is its
#: last, prev the context without it; via: the next word of the longer context that sent a table, -1 for words of the text themselves.
SEATED = "k int, ctx binary, w int, via int, depth int, a int, b int, prev binary, last int, n long"


def _pitman_yor_tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Who sits where (SEATED), of the documents of a task. A word takes a seat in all contexts up to the one before its last place in
    a phrase, so a phrase gives as many rows as its length times its distinct words at most."""
    schema = pa.schema([(c, {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}[kind]) for c, kind in (x.split() for x in SEATED.split(", "))])
    for whole in batches:
        for begin in range(0, whole.num_rows, TALLIED):
            ids, z, x = (_numbers(c.flatten()) for c in whole.slice(begin, TALLIED).columns)
            plain, n = np.unique(np.stack([z[x == 0], ids[x == 0]]), axis=1, return_counts=True)
            rows = [(k, b"", w, -1, 0, -1, -1, b"", -1, m) for k, w, m in zip(*plain.tolist(), n.tolist(), strict=True)]
            held: dict[tuple, int] = {}
            heads = np.flatnonzero(x == 0)
            ends = np.append(heads[1:], len(x))
            for begun, end in zip(heads[ends - heads > 1].tolist(), ends[ends - heads > 1].tolist(), strict=True):
                k, words = int(z[begun]), ids[begun:end].tolist()
                a, b = words[:2]
                ctxs = [b""]
                for w in words[:-1]:
                    ctxs.append(hashlib.blake2b(ctxs[-1] + w.to_bytes(4), digest_size=16).digest())
                sides = [(0, -1, -1, b"", -1), (1, a, -1, b"", a), *((i, a, b, ctxs[i - 1], words[i - 1]) for i in range(2, len(words)))]
                for j in range(1, len(words)):
                    own = (k, ctxs[j], words[j], -1, *sides[j])
                    held[own] = held.get(own, 0) + 1
                for w, j in {w: j for j, w in enumerate(words)}.items():
                    for i in range(j):
                        held[k, ctxs[i], w, words[i], *sides[i]] = 1
            rows += [(*key, m) for key, m in held.items()]
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)] if rows else [pa.array([], f.type) for f in schema], schema=schema)


def _pitman_yor_counts(now: DataFrame) -> DataFrame:
    """SEATED without via, with total and types: customers and words of the context that the word makes with its own. With one table
    for each word seen in a context, all follow from the phrases: a word's places there, and one for each longer context by a word in
    which it is seen too."""
    sides = ["depth", "a", "b", "prev", "last"]
    rows = now.select("ids", "z", "x").mapInArrow(_pitman_yor_tally, SEATED).groupBy("k", "ctx", "w", "via").agg(F.sum("n").alias("n"), *[F.first(c).alias(c) for c in sides])
    nodes = settle(rows.groupBy("k", "ctx", "w").agg(F.sum(F.when(F.col("via") < 0, F.col("n")).otherwise(1)).alias("n"), *[F.first(c).alias(c) for c in sides]), "seats")
    inside = nodes.where("depth > 0").groupBy("k", "ctx").agg(F.sum("n").alias("total"), F.count("*").alias("types"), F.first("prev").alias("prev"), F.first("last").alias("last"))
    inside = inside.select("k", F.col("prev").alias("ctx"), F.col("last").alias("w"), "total", "types")
    out = settle(nodes.join(inside, ["k", "ctx", "w"], "left").na.fill(0, ["total", "types"]), "seated")
    discard(nodes)
    return out


class Seats:
    """Customers of the contexts that a block's documents can meet. A node is a word in a context and stands for the longer context
    too; the first n_topics nodes are the topics, the next ones the block's words in each topic. ``up`` is the node of the same word
    in the context without its last word. Only one table is kept for each word seen in a context."""

    def __init__(self, words: np.ndarray, totals: np.ndarray, types: np.ndarray, rows: pa.Table, v: int, discount: float, strength: float):
        self.k, self.size, self.v, self.discount, self.strength = len(totals), len(words), v, discount, strength
        first = self.k * (self.size + 1)
        self.n, self.total, self.types, self.ctx, self.up = (np.zeros(2 * first + rows.num_rows, np.int64) for _ in range(5))
        self.total[: self.k], self.types[: self.k], self.ctx[self.k : first] = totals, types, np.repeat(np.arange(self.k), self.size)
        self.edges: dict[int, int] = {}
        self.first = self.used = first
        self.base, self.base_total, self.base_types = np.zeros(self.size, np.int64), int(types.sum()), v
        if rows.num_rows:
            self._fill(words, rows)

    def _fill(self, words: np.ndarray, rows: pa.Table) -> None:
        k, w, depth, last, n, total, types = (_numbers(rows.column(c)) for c in ("k", "w", "depth", "last", "n", "total", "types"))
        place = np.searchsorted(words, w)
        one = np.flatnonzero(depth == 0)
        at = self.k + k[one] * self.size + place[one]
        self.n[at], self.total[at], self.types[at] = n[one], total[one], types[one]
        self.base = (self.n[self.k : self.first].reshape(self.k, self.size) > 0).sum(0)
        near = np.minimum(np.searchsorted(words, last), self.size - 1)
        near[words[near] != last] = -1
        order = np.argsort(depth, kind="stable")[len(one) :]
        ctxs, prevs = (rows.column(c).take(pa.array(order)).to_pylist() for c in ("ctx", "prev"))
        known: dict[tuple, int] = {}
        find = lambda topic, ctx, w: known.get((topic, ctx, w)) if ctx else self.k + topic * self.size + w
        for topic, ctx, prev, here, before, *held in zip(k[order].tolist(), ctxs, prevs, place[order].tolist(), near[order].tolist(), n[order].tolist(), total[order].tolist(), types[order].tolist(), strict=True):
            inside = find(topic, prev, before) if before >= 0 else None
            if inside is not None:  # else the block has not all of the words, so never meets them
                s = known[topic, ctx, here] = self._new(inside, here, find(topic, prev, here))
                self.n[s], self.total[s], self.types[s] = held

    def _new(self, ctx: int, w: int, up: int) -> int:
        s = self.used
        if s == len(self.n):
            self.n, self.total, self.types, self.ctx, self.up = (np.concatenate([a, np.zeros_like(a)]) for a in (self.n, self.total, self.types, self.ctx, self.up))
        self.ctx[s], self.up[s], self.edges[ctx * self.size + w] = ctx, up, s
        self.used += 1
        return s

    def node(self, ctx: int, w: int) -> int:
        """The node of a word in a context of one word or more, made where it is missing, with those of the shorter contexts."""
        missing = []
        while ctx >= self.k and ctx * self.size + w not in self.edges:
            missing.append(ctx)
            ctx = int(self.ctx[ctx])
        s = self.edges[ctx * self.size + w] if ctx >= self.k else self.k + ctx * self.size + w
        for ctx in reversed(missing):
            s = self._new(ctx, w, s)
        return s

    def seat(self, nodes: np.ndarray, step: int) -> None:
        """A customer more (step 1) or less (-1) for each of the nodes; the first and the last of a node take a seat further up."""
        while len(nodes):
            u, m = np.unique(nodes, return_counts=True)
            before = self.n[u]
            self.n[u] += step * m
            np.add.at(self.total, self.ctx[u], step * m)
            turned = u[(before if step > 0 else self.n[u]) == 0]
            np.add.at(self.types, self.ctx[turned], step)
            top = turned[turned < self.first]
            if len(top):
                words, m = np.unique((top - self.k) % self.size, return_counts=True)
                before = self.base[words]
                self.base[words] += step * m
                self.base_total += step * len(top)
                self.base_types += step * int(((before if step > 0 else self.base[words]) == 0).sum())
            nodes = self.up[turned[turned >= self.first]]

    def heads(self, w: np.ndarray) -> np.ndarray:
        """Probability of each word (rows) at the start of a phrase of each topic."""
        d, s = self.discount, self.strength
        below = (np.maximum(self.base[w] - d, 0) + (s + d * self.base_types) / self.v) / (s + self.base_total) if self.base_total else np.full(len(w), 1 / self.v)
        n, total = self.n[self.k + np.arange(self.k) * self.size + w[:, None]], self.total[: self.k]
        return np.where(total > 0, (np.maximum(n - d, 0) + (s + d * self.types[: self.k]) * below[:, None]) / (s + total), below[:, None])

    def behind(self, ctx: np.ndarray, w: np.ndarray, heads: np.ndarray) -> np.ndarray:
        """Probability of each word behind an open phrase: discounted shares, backed off to shorter contexts as far as the topic, or as
        far as what is left can change a double of it or of the words' own (heads)."""
        d, s, get = self.discount, self.strength, self.edges.get
        p, rest, at, live = np.zeros(len(w)), np.ones(len(w)), ctx.copy(), np.arange(len(w))
        least = heads.min(axis=1) * 1e-18
        while len(live):
            if len(live) <= FEW:
                for i in live.tolist():
                    word, a, got, left, low = int(w[i]), int(at[i]), float(p[i]), float(rest[i]), float(least[i])
                    while a >= self.k and left > max(low, got * 1e-18):
                        if total := int(self.total[a]):
                            got += left * max(int(self.n[get(a * self.size + word, 0)]) - d, 0) / (s + total)
                            left *= (s + d * int(self.types[a])) / (s + total)
                        a = int(self.ctx[a])
                    p[i], rest[i], at[i] = (got, left, a) if a < self.k else (got, 0, 0)
                break
            a = at[live]
            here = np.fromiter((get(x, 0) for x in (a * self.size + w[live]).tolist()), np.int64, len(live))  # node 0 has no customers
            total = self.total[a]
            on = total > 0
            p[live] += np.where(on, rest[live] * np.maximum(self.n[here] - d, 0) / (s + total), 0)
            rest[live] *= np.where(on, (s + d * self.types[a]) / (s + total), 1)
            at[live] = self.ctx[a]
            live = live[at[live] >= self.k]
        return p + rest * heads[np.arange(len(w)), at]


def _pitman_yor_sweep(totals: np.ndarray, types: np.ndarray, discount: float, strength: float, doc_prior: float, stay: float, v: int, seed: int, sweep: int):
    """One sweep over a block's documents, from the customers of all documents at its start and the block's own changes since. Pieces
    of like size leave together, about half of a block's tokens at most or eight pieces, and are drawn anew word by word, side by side."""
    k = len(totals)

    def run(key: tuple[pa.Scalar, ...], docs: pa.Table, rows: pa.Table) -> pa.Table:
        rng = np.random.default_rng([seed, sweep, key[0].as_py()])
        docs = docs.sort_by("doc_id").combine_chunks()
        column = lambda c: docs.column(c).combine_chunks()
        sizes = _numbers(pc.list_value_length(column("ids")))
        ids, inner, z, x = (_numbers(column(c).flatten()) for c in ("ids", "inner", "z", "x"))
        z, x, tied = z.copy(), x.copy(), inner == 1
        words, w = np.unique(ids, return_inverse=True)
        seats = Seats(words, totals, types, rows, v, discount, strength)
        taken = seats.k + z * len(words) + w  # right for the first word of a phrase; the others follow it
        glued = np.flatnonzero(x == 1)
        for j, word in zip(glued.tolist(), w[glued].tolist(), strict=True):
            taken[j] = seats.edges[int(taken[j - 1]) * len(words) + word]
        of = np.repeat(np.arange(len(sizes)), sizes)
        n_doc = np.bincount((of * k + z)[x == 0], minlength=len(sizes) * k).reshape(len(sizes), k)
        start, length, doc = _pieces(sizes, inner)
        order, lanes = np.argsort(-length, kind="stable"), int(min(1024, max(8, sizes.sum() // (2 * PIECE))))
        for begin in range(0, len(order), lanes):
            group = order[begin : begin + lanes]
            left = length[group]
            gone = np.repeat(start[group] - np.cumsum(left) + left, left) + np.arange(left.sum())
            seats.seat(taken[gone], -1)
            gone = gone[x[gone] == 0]
            np.subtract.at(n_doc, (of[gone], z[gone]), 1)
            open_at = np.zeros(len(group), np.int64)
            for i in range(int(left[0])):
                live = int(np.searchsorted(-left, -i, side="left"))  # lengths fall, so the live pieces come first
                c, d = start[group[:live]] + i, doc[group[:live]]
                word, t, mine = w[c], np.flatnonzero(tied[c]), n_doc[d]
                heads = seats.heads(word)
                p = np.zeros((live, k + 1))
                p[:, :k] = (1 - stay) * (doc_prior + mine) / (doc_prior * k + mine.sum(1))[:, None] * heads
                p[t, k] = stay * seats.behind(open_at[t], word[t], heads[t])
                sums = np.cumsum(p, axis=1)
                pick = np.minimum((sums <= (rng.random(live) * sums[:, -1])[:, None]).sum(1), np.where(tied[c], k, k - 1))
                f, g = np.flatnonzero(pick < k), np.flatnonzero(pick == k)
                x[c], z[c[f]], z[c[g]] = pick == k, pick[f], z[c[g] - 1]
                open_at[f] = k + pick[f] * len(words) + word[f]
                open_at[g] = [seats.node(a, b) for a, b in zip(open_at[g].tolist(), word[g].tolist(), strict=True)]
                np.add.at(n_doc, (d[f], pick[f]), 1)
                seats.seat(open_at[:live], 1)
        offsets = pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32))
        listed = lambda a: pa.ListArray.from_arrays(offsets, pa.array(a.astype(np.int32)))
        return pa.table({**{c: docs.column(c) for c in ("block", "doc_id", "ids", "inner")}, "z": listed(z), "x": listed(x)})

    return run


def _cut_phrases(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for begin in range(0, whole.num_rows, TALLIED):
            doc, toks, z, x = whole.slice(begin, TALLIED).columns
            heads, words = np.flatnonzero(_numbers(x.flatten()) == 0), toks.flatten()
            cuts = pa.array(np.append(heads, len(words)).astype(np.int32))
            of = np.repeat(np.arange(len(doc)), _numbers(pc.list_value_length(toks)))[heads]
            phrase = pc.binary_join(pa.ListArray.from_arrays(cuts, words), " ")
            yield pa.RecordBatch.from_arrays([doc.take(pa.array(of)), phrase, pa.array(np.diff(cuts), pa.int32()), z.flatten().take(pa.array(heads))], ["doc_id", "phrase", "len", "z"])


def pitman_yor_phrases(chunks: DataFrame, n_topics: int = 5, sweeps: int = 5, discount: float = 0.5, strength: float = 1.0, doc_prior: float = 0.5, stay: float = 0.3, partitions: int = 8, seed: int = 7) -> DataFrame:
    """doc_id, phrase, len, z: joint segmentation and topics with Pitman-Yor back-off inside a phrase. Blocks of documents (at least
    ``partitions``, and one for each SEATED_TOKENS tokens) sweep from the same customers, which are counted anew from all phrases after
    each sweep; a block is sent those of contexts whose words it has. Phrases may be as long as their chunk."""
    docs, words, v = _coded(chunks)
    tokens = words.agg(F.sum("cnt")).first()[0] or 0
    blocks = max(partitions, -(-tokens // SEATED_TOKENS))
    block = topics.block_of("doc_id", topics.block_labels(chunks.sparkSession, blocks), blocks)
    now = settle(docs.select(block.alias("block"), "doc_id", "ids", "inner").mapInArrow(_pitman_yor_start(n_topics, seed), SWITCH), "seating")
    near = now.select("block", F.explode(F.transform("ids", lambda w, i: F.struct(w.alias("w"), F.get("ids", i - 1).alias("pw"), F.get("inner", i).alias("inner")))).alias("t"))
    needs = settle(near.select("block", F.col("t.w").alias("w")).distinct(), "seating-words")
    pairs = settle(near.where("t.inner = 1").select("block", F.col("t.pw").alias("a"), F.col("t.w").alias("b")).distinct(), "seating-pairs")
    begun = pairs.select("block", "a").distinct()
    for s in range(sweeps):
        nodes = _pitman_yor_counts(now)
        totals, types = np.zeros(n_topics, np.int64), np.zeros(n_topics, np.int64)
        for r in nodes.where("depth = 0").groupBy("k").agg(F.sum("n").alias("n"), F.count("*").alias("m")).collect():  # n_topics rows
            totals[r["k"]], types[r["k"]] = r["n"], r["m"]
        sent = ["block", "k", "ctx", "w", "depth", "prev", "last", "n", "total", "types"]
        one = nodes.where("depth = 0").join(needs, "w").select(*sent)
        two = nodes.where("depth = 1").join(begun, "a").select(*sent)
        more = nodes.where("depth > 1").join(pairs, ["a", "b"]).select(*sent)
        rows = one.unionByName(two.unionByName(more).join(needs, ["block", "w"]).select(*sent))
        sides = now.repartition(blocks, "block").groupBy("block"), rows.repartition(blocks, "block").groupBy("block")
        before, now = now, settle(sides[0].cogroup(sides[1]).applyInArrow(_pitman_yor_sweep(totals, types, discount, strength, doc_prior, stay, v, seed, s), SWITCH), "seating")
        if s:
            discard(before)
        discard(nodes)
    return docs.select("doc_id", "toks").join(now.select("doc_id", "z", "x"), "doc_id").select("doc_id", "toks", "z", "x").mapInArrow(_cut_phrases, "doc_id long, phrase string, len int, z int")


def rank_and_cut(counts: DataFrame, chunks: DataFrame, k: int) -> DataFrame:
    """phrase, cnt, docs, importance: the k candidates of two words or more with the largest count * log(D / documents)."""
    n_docs = chunks.agg(F.count_distinct("doc_id").alias("d"))
    most = counts.agg(F.max("n")).first()[0] or 1
    from .mining import ngrams_of

    held = chunks.select("doc_id", F.explode(F.flatten(F.array(*[ngrams_of(F.col("toks"), n) for n in range(2, max(2, most) + 1)]))).alias("phrase")).distinct().join(counts.where("n > 1").select("phrase"), "phrase").groupBy("phrase").agg(F.count("*").alias("docs"))
    rated = counts.where("n > 1").join(held, "phrase").crossJoin(n_docs).withColumn("importance", F.round(F.col("cnt") * F.log(F.col("d") / F.col("docs")), 6))
    return rated.orderBy(F.desc("importance"), "phrase").limit(k).select("phrase", "cnt", "docs", "importance")


def rule_filter(counts: DataFrame, stop_words: list[str], listed: DataFrame | None = None) -> DataFrame:
    """Candidates of 2 to 6 words without digits and without a stop word at either end; with ``listed`` only those it names."""
    ws = F.split("phrase", " ")
    ok = F.size(ws).between(2, 6) & ~F.col("phrase").rlike("[0-9]") & ~ws[0].isin(*stop_words) & ~F.element_at(ws, -1).isin(*stop_words)
    rows = counts.where(ok)
    return rows if listed is None else rows.join(listed.select("phrase").distinct(), "phrase", "left_semi")


def lda_variational(chunks: DataFrame, n_topics: int = 5, iterations: int = 10, seed: int = 7, optimizer: str = "online", vocabulary: int | None = None) -> DataFrame:
    """k, rank, word, weight: top words of the library's variational topic model. Each iteration reads all documents, and all words
    are in the vocabulary unless a size is given."""
    from pyspark.ml.clustering import LDA
    from pyspark.ml.feature import CountVectorizer

    docs = chunks.groupBy("doc_id").agg(F.flatten(F.collect_list("toks")).alias("toks"))
    vocabulary = vocabulary or max(1, chunks.select(F.explode("toks").alias("word")).distinct().count())
    bags = CountVectorizer(inputCol="toks", outputCol="features", vocabSize=vocabulary).fit(docs)
    model = LDA(k=n_topics, maxIter=iterations, seed=seed, optimizer=optimizer, subsamplingRate=1.0).fit(bags.transform(docs))
    top = model.describeTopics(10).select(F.col("topic").alias("k"), F.posexplode(F.arrays_zip("termIndices", "termWeights")).alias("rank", "t"))
    spark = chunks.sparkSession
    listed = spark.createDataFrame(list(enumerate(bags.vocabulary)), "id int, word string")
    return top.select("k", (F.col("rank") + 1).alias("rank"), F.col("t.termIndices").alias("id"), F.col("t.termWeights").alias("weight")).join(listed, "id").select("k", "rank", "word", "weight")
