import hashlib

import numpy as np
from pyspark.sql import functions as F

from phraseworks.operators import baselines, packed, topics


def _chunks(spark, n_docs: int = 40):
    rng = np.random.default_rng(3)
    rows = [(int(d) * 7 - 20, c, [f"w{i}" for i in rng.integers(0, 25, rng.integers(1, 9))]) for d in range(n_docs) for c in range(0, 2 * int(rng.integers(1, 4)), 2)]
    return spark.createDataFrame([*rows, (5_000_000_000, 0, ["one"])], "doc_id long, chunk_no int, toks array<string>")


def test_uniforms_are_those_of_the_sql():
    docs, sizes = np.array([0, -5, 2**62, 17]), np.array([130, 0, 3, 1])
    want = [int(hashlib.md5(f"7|3|{d}|{g}".encode()).hexdigest()[:8], 16) / 2**32 for d, n in zip(docs.tolist(), sizes.tolist(), strict=True) for g in range(n)]
    assert packed.uniforms(7, 3, docs, sizes).tolist() == want


def test_snapshot_on_documents_draws_what_rows_draw(spark, monkeypatch):
    """Blocks of a few tokens too; and token rows are neither sorted nor windowed."""
    chunks = _chunks(spark)
    cliques = topics.init(topics.singletons(chunks), 3)
    for s in (1, 2):
        cliques = topics.snapshot_sweep(cliques, 3, s)
    want = {(r.doc_id, r.g, r.words[0], r.z) for r in cliques.collect()}
    for tokens in (500_000, 40):
        monkeypatch.setattr(packed, "BLOCK_TOKENS", tokens)
        docs = packed.snapshot(chunks, 3, 2)
        assert {(r.doc_id, r.g, r.word, r.z) for r in packed.rows(docs).collect()} == want
    places = {(r.doc_id, r.chunk_no, r.pos, r.word) for r in chunks.select("doc_id", "chunk_no", F.posexplode("toks").alias("pos", "word")).collect()}
    assert {(r.doc_id, r.chunk_no, r.pos, r.word) for r in packed.rows(docs).collect()} == places


def test_pairs_of_packed_documents(spark):
    docs = packed.snapshot(_chunks(spark), 2, 1)
    want = {}
    for r in docs.collect():
        for i in range(1, len(r.toks)):
            if r.chunk[i] == r.chunk[i - 1] and r.z[i] == r.z[i - 1]:
                key = r.toks[i - 1], r.toks[i], r.z[i]
                want[key] = want.get(key, 0) + 1
    found = packed.adjacent_pairs(docs)
    assert {(r.v, r.w, r.k): r.n for r in found.collect()} == want
    assert "Window" not in found._jdf.queryExecution().toString()


def test_runs_of_packed_documents(spark):
    docs = spark.createDataFrame([(3, ["a", "b", "c", "d"], [0, 0, 1, 1], [0, 1, 0, 1]), (1, ["x"], [2], [0]), (2, ["p", "q", "r"], [1, 1, 0], [1, 0, 0]), (4, [], [], [])], "doc_id long, toks array<string>, z array<int>, x array<int>")
    found = packed.glued_runs(docs)
    assert {tuple(r) for r in found.collect()} == {(3, 1, "a b", 2, 0), (3, 2, "c d", 2, 1), (1, 1, "x", 1, 2), (2, 0, "p", 1, 1), (2, 1, "q", 1, 1), (2, 2, "r", 1, 0)}
    assert "Window" not in found._jdf.queryExecution().toString()
    flags = packed.same_topic(packed.snapshot(_chunks(spark), 2, 1)).join(packed.snapshot(_chunks(spark), 2, 1).select("doc_id", "pos", F.col("z").alias("z2")), "doc_id")
    for r in flags.collect():
        assert r.x == [int(p > 0 and r.z[i] == r.z[i - 1]) for i, p in enumerate(r.pos)] and r.z == r.z2


def test_drawn_slots_are_even():
    """Shares of colours drawn without replacement: sums are kept, means and spreads are those of the hypergeometric law."""
    rng, colours = np.random.default_rng(2), np.array([1, 50, 0, 300, 649])
    got = np.stack([baselines.drawn(rng, colours, 400) for _ in range(4000)])
    assert (got.sum(1) == 400).all() and (got >= 0).all() and (got <= colours).all()
    assert np.allclose(got.mean(0), colours * 0.4, atol=0.5)
    assert np.allclose(got.var(0), 0.4 * 0.6 * colours * (1000 - colours) / 999, rtol=0.15, atol=0.01)


def test_merging_writes_no_slot(spark, monkeypatch):
    """Dealt in one piece and in parts of 50 slots, the planted pair is found and joined from left to right; what is written for the
    permutations is a few rows a topic, however many slots they deal."""
    rng = np.random.default_rng(5)
    rows = [(d, c, i, w, 0) for d in range(40) for c in range(2) for i, w in enumerate(w for _ in range(10) for w in (["new", "york"] if rng.random() < 0.4 else [f"w{rng.integers(30)}"]))]
    rows += [(99, 0, i, w, z) for i, (w, z) in enumerate([("new", 0), ("york", 0), ("new", 0), ("york", 1), ("york", 0)])]
    tokens = spark.createDataFrame(rows, "doc_id long, chunk_no int, pos int, word string, z int")
    written = {}
    plain = baselines.settle
    monkeypatch.setattr(baselines, "settle", lambda df, label: written.setdefault(label, plain(df, label)))
    monkeypatch.setattr(baselines, "discard", lambda df: None)
    for deal in (8_000_000, 50):
        written.clear()
        monkeypatch.setattr(baselines, "DEAL", deal)
        out = baselines.posthoc_merge(tokens, n_perm=10, max_rounds=1)
        got = [(r.chunk_no, r.pos, r.word, r.z) for r in out.where("doc_id = 99").orderBy("pos").collect()]
        assert got == [(0, 0, "new york", 0), (0, 2, "new", 0), (0, 3, "york", 1), (0, 4, "york", 0)]
        assert out.agg(F.sum(F.size(F.split("word", " ")))).first()[0] == len(rows)
        assert written["posthoc-decks"].count() == 10
        if deal == 50:
            parts = written["posthoc-parts"]
            for side in (("ns", "nc"), ("ms", "mc")):
                slots = parts.groupBy("k", "perm").agg(F.sum(F.aggregate(F.zip_with(*side, lambda a, b: a * b), F.lit(0).cast("long"), lambda a, x: a + x)).alias("n")).select("n").distinct().collect()
                assert len(slots) == 1
            assert parts.where("part > 0").count() > 10


class _Counted:
    """A generator that counts its calls: one a step of draws."""

    def __init__(self) -> None:
        self.rng, self.steps = np.random.default_rng(3), 0

    def random(self, n: int) -> np.ndarray:
        self.steps += 1
        return self.rng.random(n)


def test_long_documents_are_drawn_in_pieces():
    """A document of 9,000 cliques takes no 9,000 steps; the counts stay those of the topics."""
    rng, k, v = np.random.default_rng(6), 4, 500
    sizes = np.array([9_000, *rng.integers(1, 400, 250), 0])
    lengths = np.where(rng.random(sizes.sum()) < 0.9, 1, rng.integers(2, 20, sizes.sum()))
    tokens, z = rng.integers(0, v, lengths.sum()), rng.integers(0, k, len(lengths))
    tally = lambda: np.bincount(tokens * k + np.repeat(z, lengths), minlength=v * k).reshape(v, k).astype(float)
    words, counted = tally(), _Counted()
    total, before = words.sum(0), z.copy()
    topics.sweep_lanes(sizes, lengths, tokens, z, words, total, np.full(k, 0.5), 0.01, v, counted)
    assert counted.steps < 1_500 and (words == tally()).all() and (total == words.sum(0)).all()
    assert 0.5 < (z != before).mean() < 0.95 and z.min() == 0 and z.max() == k - 1


def test_snapshot_of_packed_cliques_draws_what_rows_draw(spark, monkeypatch):
    """Repeated words in a clique, long cliques and blocks of a few tokens too; and the state needs neither joins nor windows by row."""
    rng = np.random.default_rng(8)
    rows = []
    for d in range(30):
        for g in range(int(rng.integers(1, 12))):
            words = [f"w{i}" for i in rng.integers(0, 9, 1 if rng.random() < 0.6 else rng.integers(2, 25))]
            rows.append((d * 5 - 20, g, len(words), " ".join(words)))
    rows += [(5_000_000_000, 0, 1, "one"), (5_000_000_000, 1, 3, "one one one")]
    parts = spark.createDataFrame(rows, "doc_id long, g int, len int, phrase string")
    state = topics.init(topics.make_cliques(parts), 3)
    for s in (1, 2):
        state = topics.snapshot_sweep(state, 3, s)
    want = {(r.doc_id, r.g, tuple(r.words), r.z) for r in state.collect()}
    assert len(want) == len(rows)
    for tokens, held in ((500_000, 65_536), (40, 7)):
        monkeypatch.setattr(packed, "BLOCK_TOKENS", tokens)
        monkeypatch.setattr(packed, "SLICE", held)
        found = packed.snapshot_cliques(parts, 3, 2)
        assert {(r.doc_id, r.g, tuple(r.words), r.z) for r in found.collect()} == want
