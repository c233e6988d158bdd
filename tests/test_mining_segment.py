"""Worked corpora, invariants and brute force for mining and segmentation."""

import random
from collections import Counter

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from phraseworks.functions import text
from phraseworks.functions.stem import stem
from phraseworks.operators import mining, segment
from phraseworks.plans.pipeline import Config, Stages
from phraseworks.sources import io

M1 = {"frequent pattern mine": 6, "mine frequent pattern": 4, "frequent pattern tree approach": 2, "tree search": 5, "approach search": 3, "mine": 5, "data stream": 6, "data": 4, "frequent data": 1}
M2 = {"mine frequent pattern candidate generation": 1, "frequent pattern tree approach": 1, "frequent pattern mine": 7, "current status future direction": 1, "mine frequent pattern": 5, "frequent pattern": 8, "tree search": 4, "frequent query": 3, "mine": 3, "data stream": 40}


def stages(spark, corpus, **config):
    rows = [t for t, n in corpus.items() for _ in range(n)]
    return Stages(spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string"), Config(**config))


def units(mined, threshold, kernel="heap"):
    u = segment.segment_unique(mined, threshold, kernel)
    return {r[0]: list(r[1]) for r in u.select(F.concat_ws(" ", "toks"), F.transform("units", lambda x: segment.phrase_of(F.col("toks"), x))).collect()}


@pytest.fixture(scope="module")
def one(spark):
    return stages(spark, M1, min_support=3, max_len=None, sig_threshold=1.0)


def test_counts(one):
    got = {r["phrase"]: r["cnt"] for r in one.mined.counts.collect()}
    assert one.mined.tokens == 77
    assert got == {"frequent": 13, "pattern": 12, "mine": 15, "tree": 7, "approach": 5, "search": 8, "data": 11, "stream": 6, "frequent pattern": 12, "pattern mine": 6, "mine frequent": 4, "tree search": 5, "approach search": 3, "data stream": 6, "frequent pattern mine": 6, "mine frequent pattern": 4}


def test_variants(one):
    literal = mining.frequent_phrases(one.chunks, 3, None, boundary_rule="as_printed").counts.where("n > 1")
    assert {r["phrase"]: r["cnt"] for r in literal.collect()} == {"frequent pattern": 8, "mine frequent": 4}
    exact = {tuple(r) for r in one.mined.counts.collect()}
    assert {tuple(r) for r in mining.frequent_phrases(one.chunks, 3, 3, prune_positions=False).counts.collect()} == exact
    assert {tuple(r) for r in mining.frequent_phrases(one.chunks, 3, 6, prune_docs=False).counts.collect()} == exact
    assert {tuple(r) for r in mining.sketch_filtered(one.chunks, 3).collect()} == {(p, c) for n, p, c in exact if n == 2}


@pytest.mark.parametrize("kernel", ["heap", "expr"])
def test_merges(one, kernel):
    assert units(one.mined, 1.0, kernel) == {"mine frequent pattern": ["mine", "frequent pattern"], "frequent pattern mine": ["frequent pattern mine"], "frequent pattern tree approach": ["frequent pattern", "tree", "approach"], "tree search": ["tree search"], "approach search": ["approach search"], "data stream": ["data stream"], "frequent data": ["frequent", "data"], "mine": ["mine"], "data": ["data"]}


def test_trace(one):
    steps = {(r["chunk"], r["step"]): round(r["sig"], 6) for r in segment.trace(one.mined, 1.0).collect()}
    assert steps[("frequent pattern mine", 1)] == 2.879253 and steps[("frequent pattern mine", 2)] == 1.495143
    assert steps[("tree search", 1)] == 1.910822 and ("frequent data", 1) not in steps


def test_titles(spark):
    s = stages(spark, M2, min_support=3, max_len=None, sig_threshold=1.5)
    got = units(s.mined, 1.5)
    assert s.mined.tokens == 162
    assert got["mine frequent pattern candidate generation"] == ["mine frequent pattern", "candidate", "generation"]
    assert got["frequent pattern tree approach"] == ["frequent pattern", "tree", "approach"]
    assert got["frequent pattern mine"] == ["frequent pattern mine"]
    assert got["current status future direction"] == ["current", "status", "future", "direction"]


def test_greedy_is_global():
    scores = {(0, 1, 1): 10, (1, 1, 1): 1, (2, 1, 1): 5, (0, 2, 1): 8}
    counts = {(i, n): 1 for i in range(4) for n in range(1, 5 - i)}
    got, _ = segment.merge_chunk(4, counts, 4, 1, scorer=lambda at, a, b: scores.get((at, a, b)))
    assert got == [(0, 3), (3, 1)]


def test_threshold_pushdown(spark, one):
    full, pruned = units(one.mined, 2.0), units(mining.frequent_phrases(one.chunks, 3, None, for_threshold=2.0), 2.0)
    assert full == pruned


@settings(max_examples=60, deadline=None)
@given(st.lists(st.sampled_from("abcd"), min_size=1, max_size=14), st.integers(0, 10**6))
def test_heap_equals_rescan(toks, seed):
    """The heap takes the same merges as looking at all pairs anew each time."""
    rng = random.Random(seed)
    counts = {}
    for n in (1, 2, 3, 4):
        for i in range(len(toks) - n + 1):
            counts[" ".join(toks[i : i + n])] = rng.randint(3, 60)
    spans = {(i, n): counts[" ".join(toks[i : i + n])] for n in (1, 2, 3, 4) for i in range(len(toks) - n + 1)}
    cur = [(i, 1) for i in range(len(toks))]
    while True:
        best = None
        for i, ((a, n), (b, m)) in enumerate(zip(cur, cur[1:], strict=False)):
            if (a, n + m) in spans:
                s = segment.score_value(spans[a, n], spans[b, m], spans[a, n + m], 500)
                if s >= 2 and (best is None or s > best[0]):
                    best = (s, i)
        if best is None:
            break
        i = best[1]
        cur[i : i + 2] = [(cur[i][0], cur[i][1] + cur[i + 1][1])]
    assert segment.merge_chunk(len(toks), spans, 2, 500)[0] == cur


def test_mining_equals_exhaustive(spark):
    rng = random.Random(5)
    rows = [(i, " ".join(rng.choice("abcde") for _ in range(rng.randint(0, 12))), "xx") for i in range(200)]
    chunks = text.chunk(spark.createDataFrame(rows, "doc_id long, text string, lang string"), keep=("lang",))
    truth = Counter(" ".join(w[i : i + n]) for _, t, _ in rows for w in [t.split()] for n in range(1, 6) for i in range(len(w) - n + 1))
    got = {r["phrase"]: r["cnt"] for r in mining.frequent_phrases(chunks, 6, 5).counts.collect()}
    assert got == {p: c for p, c in truth.items() if c >= 6}
    for p in got:
        ws = p.split()
        assert len(ws) == 1 or (got[" ".join(ws[1:])] >= got[p] and got[" ".join(ws[:-1])] >= got[p])


def test_degenerate_text(spark):
    rows = [(0, "x " * 300, "en"), (1, "", "en"), (2, "!!! ... ,,", "en"), (3, "the and of", "en"), (4, "one", "en"), (5, None, "en"), (6, "éa ñb öc", "xx"), (7, "éa ñb öc", "xx"), (8, "a.b,c;d:e!f?g(h)i[j]k{l}m", None)]
    s = Stages(spark.createDataFrame(rows, "doc_id long, text string, lang string"), Config(min_support=2, max_len=4, sig_threshold=0.5))
    assert segment.check_partition(s.parts, s.chunks).count() == 0
    assert {r["doc_id"] for r in s.chunks.select("doc_id").distinct().collect()} == {0, 4, 6, 7, 8}
    assert text.collapse_runs(s.chunks, 3).where("doc_id = 0").first()["toks"] == ["x"] * 3
    empty = spark.createDataFrame([], "doc_id long, text string, lang string")
    assert Stages(empty, Config()).parts.count() == 0


@pytest.mark.parametrize(("word", "want"), [("caresses", "caress"), ("ponies", "poni"), ("cats", "cat"), ("agreed", "agre"), ("plastered", "plaster"), ("motoring", "motor"), ("sing", "sing"), ("conflated", "conflat"), ("hopping", "hop"), ("falling", "fall"), ("filing", "file"), ("happy", "happi"), ("sky", "sky"), ("relational", "relat"), ("conditional", "condit"), ("vietnamization", "vietnam"), ("triplicate", "triplic"), ("hopeful", "hope"), ("goodness", "good"), ("revival", "reviv"), ("adoption", "adopt"), ("probate", "probat"), ("rate", "rate"), ("controll", "control"), ("roll", "roll"), ("generalizations", "gener")])
def test_stems(word, want):
    assert stem(word) == want


def test_phrases_of_any_length(spark):
    """Without a cap mining goes on to the longest frequent phrase; a cap is an option."""
    line = [f"w{i}" for i in range(9)]
    df = spark.createDataFrame([(i, line) for i in range(3)] + [(3, line[:4])], "doc_id long, toks array<string>")
    want = {(n, " ".join(line[i : i + n])): 4 if i + n <= 4 else 3 for n in range(1, 10) for i in range(10 - n)}
    got = lambda **o: {(r["n"], r["phrase"]): r["cnt"] for r in mining.frequent_phrases(df, 3, **o).counts.collect()}
    assert got() == want == got(prune_positions=False)
    assert got(max_len=6) == {k: c for k, c in want.items() if k[0] <= 6}
    assert Config().max_len is None


def exhaustive(rows, least):
    truth = Counter(" ".join(w[i : i + n]) for w in rows for n in range(1, len(w) + 1) for i in range(len(w) - n + 1))
    return {p: c for p, c in truth.items() if c >= least}


def test_doubled_lengths_equal_exhaustive(spark, monkeypatch):
    """Runs of one word, copied lines and chance repeats, by steps of one word and by doubling from two words on: the same phrases,
    spans and partitions; documents as the unit of support too."""
    rng = random.Random(8)
    line = [f"w{i}" for i in range(23)]
    rows = [["x"] * 70, ["x"] * 41, ["x", "y"] * 20] + [line[rng.randint(0, 6) : rng.randint(9, 23)] for _ in range(12)] + [[rng.choice("abc") for _ in range(rng.randint(1, 15))] for _ in range(60)]
    df = spark.createDataFrame([(i, r) for i, r in enumerate(rows)], "doc_id long, toks array<string>")
    want, seen = exhaustive(rows, 4), []
    for steps in (2, 3, 8):
        monkeypatch.setattr(mining, "STEPS", steps)
        m = mining.frequent_phrases(df, 4)
        assert {r["phrase"]: r["cnt"] for r in m.counts.collect()} == want
        spans = m.spans.join(m.chunks, "uid").select(F.concat_ws(" ", F.slice("toks", F.col("at") + 1, F.col("n"))).alias("p"), "cnt", "mult").groupBy("p").agg(F.max("cnt").alias("c"), F.sum("mult").alias("m")).collect()
        assert {r["p"]: (r["c"], r["m"]) for r in spans} == {p: (c, c) for p, c in want.items() if " " in p}
        seen.append({(tuple(r["toks"]), tuple(map(tuple, r["units"]))) for r in segment.segment_unique(m, 1.0).select("toks", "units").collect()})
    assert seen[0] == seen[1] == seen[2]
    monkeypatch.setattr(mining, "STEPS", 2)
    held = Counter(p for r in rows for p in {" ".join(r[i : i + n]) for n in range(1, len(r) + 1) for i in range(len(r) - n + 1)})
    by_doc = mining.frequent_phrases(df, 4, support_by="document").counts
    assert {r["phrase"]: r["cnt"] for r in by_doc.collect()} == {p: c for p, c in held.items() if c >= 4}
    capped = mining.frequent_phrases(df, 4, 7).counts
    assert {r["phrase"]: r["cnt"] for r in capped.collect()} == {p: c for p, c in want.items() if p.count(" ") < 7}


def edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        row, last = [i], row
        for j, y in enumerate(b, 1):
            row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
    return row[-1]


@pytest.mark.parametrize("bound", [0, 1, 2, 3])
def test_similar_by_edits(spark, bound):
    rng = random.Random(bound)
    words = {"kitten", "sitting", "a", "é", "ab", "naïve", "naive", "b"} | {"".join(rng.choice("abé") for _ in range(rng.randint(1, 9))) for _ in range(150)}
    phrases = sorted(words | {f"{rng.choice(sorted(words))} {rng.choice(sorted(words))}" for _ in range(60)})
    counts = spark.createDataFrame([(p.count(" ") + 1, p) for p in phrases], "n int, phrase string")
    want = {(a, b) for i, a in enumerate(phrases) for b in phrases[i + 1 :] if a.count(" ") == b.count(" ") and edits(a, b) <= bound}
    assert {tuple(r) for r in mining.tie_similar(counts, "edit", bound).collect()} == want
    assert bound < 3 or ("kitten", "sitting") in want


@pytest.mark.parametrize("bound", [0.3, 0.5, 0.6, 1.0])
def test_similar_by_words_and_stems(spark, bound):
    rng = random.Random(3)
    phrases = sorted({" ".join(rng.choice(["cat", "cats", "run", "running", "tree", "trees", "a", "b"]) for _ in range(rng.randint(1, 5))) for _ in range(200)})
    counts = spark.createDataFrame([(p.count(" ") + 1, p) for p in phrases], "n int, phrase string")
    sets = {p: set(p.split()) for p in phrases if " " in p}
    want = {(a, b) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= bound}
    assert {tuple(r) for r in mining.tie_similar(counts, "jaccard", bound).collect()} == want
    stems = {p: [stem(w) for w in p.split()] for p in phrases}
    assert {tuple(r) for r in mining.tie_similar(counts, "stem").collect()} == {(a, b) for a in phrases for b in phrases if a < b and stems[a] == stems[b]}
    with pytest.raises(ValueError, match="whole number"):
        mining.tie_similar(counts, "edit", 1.5)


def test_raw_titles_are_stemmed_and_shown_as_written(spark):
    """From raw titles to brackets: inflected words count as one, and views show the most frequent written form."""
    rows = [(i, t, "en") for i, t in enumerate(["Mining frequent patterns", "Mining frequent patterns", "Mined frequent patterns.", "The mining of frequent patterns", "Frequent pattern, and others", "Mining the frequent patterns"] * 3)]
    s = Stages(spark.createDataFrame(rows, "doc_id long, text string, lang string"), Config(min_support=3, sig_threshold=1.0, stem=True, n_topics=2, sweeps=3))
    counts = {r["phrase"]: r["cnt"] for r in s.mined.counts.collect()}
    assert counts["mine"] == 15 and counts["frequent pattern"] == 18 and counts["mine frequent"] == 15
    shown = {r["phrase"]: r["surface"] for r in s.surfaces.collect()}
    assert shown["mine frequent pattern"] == "mining frequent patterns"
    assert {r["word"]: r["surface"] for r in s.word_surfaces.collect()}["pattern"] == "patterns"
    view = s.view(s.fit().state)
    assert {r["text"] for r in view.where("kind = 'word'").collect()} <= {"mining", "frequent", "patterns", "others"}


def test_table_function_segments_texts(spark):
    from phraseworks.functions import sqlsurface

    rows = [(i, "new york is large; new york city", "en") for i in range(6)] + [(9, "a café, york", "fr")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    s = Stages(docs, Config(min_support=3, sig_threshold=0.5))
    sqlsurface.register(spark, s.mined.counts, 0.5, s.mined.tokens)
    docs.createOrReplaceTempView("pw_docs")
    got = spark.sql("SELECT d.doc_id, p.chunk_no, p.start, p.phrase FROM pw_docs d, LATERAL phrases(d.text, d.lang) p")
    want = s.parts.select("doc_id", "chunk_no", "start", "phrase")
    assert Counter(map(tuple, got.collect())) == Counter(map(tuple, want.collect()))
    words = spark.sql("SELECT w.word, w.kept FROM pw_docs d, LATERAL phrase_words(d.text, d.lang) w WHERE d.doc_id = 9")
    assert [tuple(r) for r in words.collect()] == [("a", True), ("café", True), ("york", True)]


def test_similar_phrases_never_broadcast_their_keys(spark, tmp_path):
    """A phrase has some 75 keys, which the size of its table does not show."""
    spark.createDataFrame([(2, f"word{i} other{i}", 10) for i in range(50)], "n int, phrase string, cnt long").write.parquet(f"{tmp_path}/counts")
    found = mining.tie_similar(spark.read.parquet(f"{tmp_path}/counts"), "edit", 2)
    assert "Broadcast" not in found._jdf.queryExecution().executedPlan().toString()
    phrases = [f"word{i} other{i}" for i in range(50)]
    assert {(r["a"], r["b"]) for r in found.collect()} == {(a, b) for a in phrases for b in phrases if a < b and edits(a, b) <= 2}


def test_phrases_are_listed_after_the_order_of_chunks(spark):
    """Documents are put in order by rows of chunks, not by rows of phrases, and places count through a document."""
    chunks = spark.createDataFrame([(d, c, ["new", "york", "is", f"w{d}"][: 4 - c]) for d in range(30) for c in range(3)], "doc_id long, chunk_no int, toks array<string>")
    parts = segment.partition(chunks, mining.frequent_phrases(chunks, 5), 3.0)
    plan = parts._jdf.queryExecution().optimizedPlan().toString()
    assert 0 <= plan.index("Generate posexplode") < plan.index("Window")
    got = [tuple(r) for r in parts.where("doc_id = 4").orderBy("g").select("chunk_no", "g", "start", "len", "phrase").collect()]
    assert got == [(0, 0, 0, 3, "new york is"), (0, 1, 3, 1, "w4"), (1, 2, 0, 3, "new york is"), (2, 3, 0, 2, "new york")]


def test_mining_keeps_no_tables_that_nothing_reads(spark, tmp_path, monkeypatch):
    """Candidates and one-word positions go once the next level is written; long phrases meet by a sort-merge join."""
    monkeypatch.setattr(io, "shared_folder", lambda _: f"file://{tmp_path}")
    plans, real = {}, io.settle
    monkeypatch.setattr(mining, "settle", lambda df, label: (plans.setdefault(label, df._jdf.queryExecution().executedPlan().toString()), real(df, label))[1])
    passage = [f"w{i}" for i in range(20)]
    mined = mining.frequent_phrases(spark.createDataFrame([(d, [*passage, f"x{d}"]) for d in range(12)], "doc_id long, toks array<string>"), 10)
    assert mined.counts.where("n > 1").count() == 20 * 19 // 2 and mined.spans.count() == 12 * 20 * 19 // 2
    left = {p.name.rsplit("-", 1)[0] for p in tmp_path.iterdir()}
    assert not [x for x in left if x.startswith(("candidates", "pairs"))] and "alive-1" not in left and "alive-2" in left
    assert "level-16" in plans and "BroadcastHashJoin" not in plans["level-16"]


def test_single_words_need_no_raw_chunks(spark, monkeypatch):
    """Surfaces of single words don't go through the join with the raw chunks; phrases keep their stop words, and stems their forms."""
    seen, real = [], text.surface
    monkeypatch.setattr(text, "surface", lambda raw, spans, *rest: (seen.append(spans), real(raw, spans, *rest))[1])
    docs = spark.createDataFrame([(d, f"bank of england rates w{d}", "en") for d in range(20)], "doc_id long, text string, lang string")
    got = {r["phrase"]: (r["surface"], r["cnt"]) for r in Stages(docs, Config(min_support=10, sig_threshold=2.0)).surfaces.collect()}
    assert got["bank england rates"] == ("bank of england rates", 20) and got["w3"] == ("w3", 1) and len(got) == 21
    assert seen[0].count() == 20


@pytest.mark.parametrize("bound", [0, 1, 2, 4])
def test_short_and_long_phrases_meet_by_edits(spark, bound):
    """Around the length at which keys change, with the empty text, one letter, and letters of more than one byte."""
    rng = random.Random(bound)
    phrases = {"", "a", "é", "ab"}
    for size in (3, 5, 6, 7, 12, 13, 14, 15, 16, 99, 100, 101):
        for _ in range(4):
            text = [rng.choice("abß") for _ in range(size)]
            phrases.add("".join(text))
            for _ in range(bound):
                i = rng.randrange(len(text) + 1)
                text[i : i + rng.randint(0, 1)] = rng.choice(["", "a", "ßb"])[:1]
            phrases.add("".join(text))
    phrases = sorted(phrases)
    counts = spark.createDataFrame([(1, p) for p in phrases], "n int, phrase string")
    want = {(a, b) for i, a in enumerate(phrases) for b in phrases[i + 1 :] if abs(len(a) - len(b)) <= bound and edits(a, b) <= bound}
    assert {tuple(r) for r in mining.tie_similar(counts, "edit", bound).collect()} == want


def test_similar_words_do_not_meet_by_a_few_letters(spark):
    """3,000 words that begin alike: few meet as candidates, not each pair of words."""
    rng = random.Random(9)
    words = sorted({f"zz{''.join(rng.choice('abcdefghijklmnopqrstuvwxy') for _ in range(6))}" for _ in range(3000)})
    short, keyed = mining.edit_keys(spark.createDataFrame([(1, w) for w in words], "n int, phrase string"), 2)
    met = keyed.groupBy("key").agg(F.count("*").alias("m")).agg(F.sum(F.col("m") * (F.col("m") - 1) / 2)).first()[0]
    assert short >= 8 and met < 30_000 < len(words) ** 2 / 100
