"""The topic model against its joint law, conservation, planted topics and special cases."""

import itertools
import math
import time

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from phraseworks.operators import baselines, evaluate, rank, topics

PRIOR, BETA, V = np.array([0.3, 0.5, 0.7]), 0.1, 4


def log_joint(docs, z):
    """Log of the collapsed joint of words and topics, whole cliques in one topic."""
    k, lg = len(PRIOR), math.lgamma
    nk, nxk, out = np.zeros(k), np.zeros((V, k)), 0.0
    for d, zs in zip(docs, z, strict=True):
        nd = np.zeros(k)
        for c, t in zip(d, zs, strict=True):
            nd[t] += len(c)
            nk[t] += len(c)
            for w in c:
                nxk[w, t] += 1
        out += sum(lg(a + n) for a, n in zip(PRIOR, nd, strict=True)) - lg(PRIOR.sum() + nd.sum())
    return out + sum(lg(BETA + x) for x in nxk.ravel()) - sum(lg(V * BETA + n) for n in nk)


def conditional(docs, z, d, g, repeat_offset=True):
    nd, nk, nxk = np.zeros(3), np.zeros(3), np.zeros((V, 3))
    for i, (dd, zz) in enumerate(zip(docs, z, strict=True)):
        for j, (c, t) in enumerate(zip(dd, zz, strict=True)):
            if (i, j) != (d, g):
                nk[t] += len(c)
                nd[t] += len(c) * (i == d)
                for w in c:
                    nxk[w, t] += 1
    w = topics.weights_of(np.array(docs[d][g]), nd, nxk, nk, PRIOR, BETA, V, repeat_offset)
    return w / w.sum()


@pytest.mark.parametrize(("docs", "d", "g", "want"), [([[[0, 1], [2]], [[0], [1, 2, 3]]], 0, 0, (0.110048597, 0.274337670, 0.615613733)), ([[[0, 1], [2]], [[0], [1, 2, 3]]], 1, 1, (0.077047672, 0.506166022, 0.416786306)), ([[[0, 0], [2]], [[0], [1, 2, 1]]], 0, 0, (0.083990472, 0.019034360, 0.896975168)), ([[[0, 0], [2]], [[0], [1, 2, 1]]], 1, 1, (0.007531893, 0.544289904, 0.448178203))])
def test_conditional_is_the_joints(docs, d, g, want):
    z = [[0, 1], [2, 1]]
    logs = []
    for k in range(3):
        zz = [list(x) for x in z]
        zz[d][g] = k
        logs.append(log_joint(docs, zz))
    p = np.exp(np.array(logs) - max(logs))
    p /= p.sum()
    assert np.allclose(p, want, atol=1e-9)
    assert np.allclose(conditional(docs, z, d, g), p, atol=1e-12)


def test_published_form_differs_on_repeats():
    got = conditional([[[0, 0], [2]], [[0], [1, 2, 1]]], [[0, 1], [2, 1]], 0, 0, repeat_offset=False)
    assert np.allclose(got, (0.015933509, 0.003610935, 0.980455556), atol=1e-9)


def test_hard_potential_is_the_limit_of_a_soft_one():
    """All states of one clique under a penalty for each pair of words with different topics: its mass moves to the K uniform ones."""
    docs, z = [[[0, 1], [2]], [[0], [1, 2, 3]]], [[0, 1], [2, 1]]
    k_states = list(itertools.product(range(3), repeat=2))
    for penalty, least in ((1.0, 0.0), (20.0, 0.999)):
        mass = {}
        for s in k_states:
            flat = [[[0], [1], [2]], [[0], [1, 2, 3]]]
            mass[s] = math.exp(log_joint(flat, [[s[0], s[1], z[0][1]], z[1]]) - penalty * (s[0] != s[1]))
        total = sum(mass.values())
        assert sum(mass[k, k] for k in range(3)) / total >= least
    hard = np.array([mass[k, k] for k in range(3)])
    assert np.allclose(hard / hard.sum(), conditional(docs, z, 0, 0), atol=1e-9)


@pytest.fixture(scope="module")
def planted(spark):
    """Three blocks of words; each document draws from one, with fixed pairs as phrases."""
    rng = np.random.default_rng(3)
    rows = []
    for d in range(60):
        t = d % 3
        for g in range(20):
            i = int(rng.integers(0, 6))
            words = [f"t{t}a{i}", f"t{t}b{i}"] if g % 2 else [f"t{t}c{i}"]
            rows.append((d, g, words))
    return spark.createDataFrame(rows, "doc_id long, g int, words array<string>").cache()


@pytest.mark.parametrize("mode", ["exact", "partitioned", "snapshot"])
def test_planted_topics(spark, planted, mode):
    model = topics.fit(planted, 3, sweeps=25 if mode != "snapshot" else 8, doc_prior=0.1, mode=mode, partitions=3)
    truth = planted.select("doc_id").distinct().withColumn("block", (F.col("doc_id") % 3).cast("string"))
    assert evaluate.agreement(evaluate.dominant_topic(model.state), truth, "block").first()["purity"] > (0.95 if mode != "snapshot" else 0.5)
    if mode == "exact":
        view = rank.topic_view(model.state)
        assert {r["text"] for r in view.where("kind = 'phrase'").collect()} == {f"t{t}a{i} t{t}b{i}" for t in range(3) for i in range(6)}
    word, doc, total = topics.counts(model.state)
    n = planted.agg(F.sum(F.size("words"))).first()[0]
    assert [x.agg(F.sum("cnt")).first()[0] for x in (word, doc, total)] == [n] * 3
    assert model.state.count() == planted.count()
    tf = rank.topical_frequency(model.state).groupBy("phrase").agg(F.sum("tf").alias("tf"))
    assert {tuple(r) for r in tf.collect()} == {tuple(r) for r in planted.groupBy(F.concat_ws(" ", "words")).count().collect()}


def test_distributions_sum_to_one(spark, planted):
    state = topics.init(planted, 4)
    for rows, key in ((topics.theta(state, 4), "doc_id"), (topics.phi(state, 4).withColumnRenamed("phi", "theta"), "k")):
        off = rows.groupBy(key).agg(F.abs(F.sum("theta") - 1).alias("off")).agg(F.max("off")).first()[0]
        assert off < 1e-9


def test_same_seed_same_result_and_word_model_is_a_special_case(spark, planted):
    single = planted.select("doc_id", F.col("g").alias("chunk_no"), F.col("words").alias("toks"))
    a = baselines.lda(single, n_topics=3, sweeps=3, mode="exact", doc_prior=0.5).state
    b = topics.fit(topics.singletons(single), 3, sweeps=3, mode="exact", doc_prior=0.5).state
    assert {(r.doc_id, r.g, r.z) for r in a.collect()} == {(r.doc_id, r.g, r.z) for r in b.collect()}


def test_perplexity_falls_and_priors_move(spark, planted):
    model = topics.fit(planted, 3, sweeps=12, doc_prior=0.5, mode="exact", trace_every=4, optimise_every=4)
    seen = [t["perplexity"] for t in model.trace]
    assert seen[-1] < seen[0] and np.isfinite(seen).all()
    assert (model.doc_prior != 0.5).all()
    assert topics.word_prior_step(model.state, 3, 0.01) > 0
    thetas = topics.infer(planted, topics.phi(model.state, 3), 3)
    assert abs(thetas.agg(F.sum("theta")).first()[0] - 60) < 1e-6


def test_auto_topics(spark, planted):
    model = topics.fit(planted, "auto", sweeps=20, k_max=8, mode="exact", concentration=0.5)
    use = {r["k"]: r["cnt"] for r in topics.counts(model.state)[2].collect()}
    assert model.n_topics == 8 and sum(use.values()) == planted.agg(F.sum(F.size("words"))).first()[0]
    most, least = max(use, key=use.get), min(range(8), key=lambda k: use.get(k, 0))
    assert model.doc_prior[most] > model.doc_prior[least]
    truth = planted.select("doc_id").distinct().withColumn("block", (F.col("doc_id") % 3).cast("string"))
    assert evaluate.agreement(evaluate.dominant_topic(model.state), truth, "block").first()["purity"] > 0.9


def test_baselines_find_planted_pairs(spark):
    rng = np.random.default_rng(1)
    rows = [(d, 0, [w for _ in range(12) for w in (["new", "york"] if rng.random() < 0.4 else [f"w{rng.integers(30)}"])]) for d in range(60)]
    chunks = spark.createDataFrame(rows, "doc_id long, chunk_no int, toks array<string>")
    glued = baselines.bigram_switch(chunks, n_topics=2, sweeps=15).where("len > 1").groupBy("phrase").count().orderBy(F.desc("count")).first()
    assert glued["phrase"] == "new york"
    best = baselines.pitman_yor_phrases(chunks, n_topics=2, sweeps=5).where("len > 1").groupBy("phrase").count().orderBy(F.desc("count")).first()
    assert "new york" in best["phrase"]
    tokens = chunks.select("doc_id", "chunk_no", F.posexplode("toks").alias("pos", "word")).withColumn("z", F.lit(0))
    merged = baselines.posthoc_merge(tokens, n_perm=10, max_rounds=1)
    assert merged.where("word = 'new york'").count() > 100
    sets = baselines.itemset_keyphrases(tokens, min_support=10, complete=0.0).where(F.size("items") == 2)
    assert sets.where(F.array_contains("items", "new") & F.array_contains("items", "york")).count() == 1
    with pytest.raises(ValueError, match="transaction"):
        baselines.itemset_keyphrases(tokens, largest_set=3)
    many = spark.createDataFrame([(d, 0, i, f"w{i}", 0) for d in range(2) for i in range(6000)], "doc_id long, chunk_no int, pos int, word string, z int")
    assert baselines.itemset_keyphrases(many.where("pos < 40 or doc_id = 0"), min_support=2, complete=0.0).where(F.size("items") == 2).count() == 40 * 39 // 2


def test_switch_counts_are_merged(spark):
    """Blocks start every sweep from the counts of all documents: what one block has seen shows in the others."""
    rng = np.random.default_rng(4)
    rows = [(d, 0, [w for _ in range(8) for w in (["new", "york"] if rng.random() < 0.4 else [f"w{rng.integers(20)}"])]) for d in range(80)]
    chunks = spark.createDataFrame(rows, "doc_id long, chunk_no int, toks array<string>")
    got = baselines.bigram_switch(chunks, n_topics=2, sweeps=12, partitions=8)
    pairs = sum(t[i : i + 2] == ["new", "york"] for _, _, t in rows for i in range(len(t)))
    assert got.where("phrase = 'new york'").count() > 0.5 * pairs
    assert got.agg(F.sum("len")).first()[0] == sum(len(t) for _, _, t in rows)


def test_switch_block_at_speed():
    """A block of 60,000 tokens sweeps well within a second or two (token by token it took many times that), documents over a piece's
    length included; the counts it starts from are those of a plain loop."""
    rng = np.random.default_rng(6)
    sizes = [9_000, *[int(n) for n in rng.integers(1, 400, 250)]]
    ids = [rng.integers(0, 500, n).tolist() for n in sizes]
    inner = [[int(i % 7 > 0) for i in range(n)] for n in sizes]
    z = [rng.integers(0, 4, n).tolist() for n in sizes]
    x = [(rng.integers(0, 2, n) * np.array(m)).tolist() for n, m in zip(sizes, inner, strict=True)]
    ints = pa.list_(pa.int32())
    docs = pa.table({"block": pa.array([3] * len(sizes), pa.int32()), "doc_id": pa.array(range(len(sizes)), pa.int64()), "ids": pa.array(ids, ints), "inner": pa.array(inner, ints), "z": pa.array(z, ints), "x": pa.array(x, ints)})
    tally = lambda t: pa.Table.from_batches(baselines._switch_tally(500)(t.select(["ids", "inner", "z", "x"]).combine_chunks().to_batches())).to_pandas().groupby(["kind", "a", "b", "c"]).n.sum()
    counts = tally(docs).reset_index()
    plain = {}
    for w, m, k, f in zip(ids, inner, z, x, strict=True):
        for i in range(len(w)):
            for item in [(0, k[i], w[i], 0)] if not f[i] else [(1, k[i], w[i - 1], w[i]), (2, k[i], w[i - 1], 0)]:
                plain[item] = plain.get(item, 0) + 1
            if m[i]:
                plain[3, k[i - 1], w[i - 1], f[i]] = plain.get((3, k[i - 1], w[i - 1], f[i]), 0) + 1
    assert tally(docs).to_dict() == plain
    nk = counts[counts.kind == 0].groupby("a").n.sum().to_numpy().astype(float)
    begin = time.process_time()
    out = baselines._switch_sweep(4, nk, 0.5, 0.01, 0.1, 0.01, 500, 7, 0)((pa.scalar(3),), docs, pa.Table.from_pandas(counts))
    assert time.process_time() - begin < 3
    assert out.column("ids").to_pylist() == ids and out.column("doc_id").to_pylist() == list(range(len(sizes)))
    flags = np.concatenate(out.column("x").to_pylist())
    assert not flags[np.concatenate(inner) == 0].any() and 0 < flags.mean() < 1 and np.concatenate(out.column("z").to_pylist()).max() < 4
    start, length, doc = baselines._pieces(np.array(sizes), np.concatenate(inner))
    assert length.sum() == sum(sizes) and (np.concatenate(inner)[start] == 0).all() and length.max() <= baselines.PIECE + 7 and set(doc) == set(range(len(sizes)))


def test_permutations_in_parts(spark, monkeypatch):
    """Successors dealt within parts of a topic find the planted pair as those dealt in the whole do."""
    rng = np.random.default_rng(5)
    rows = [(d, 0, i, w, 0) for d in range(60) for i, w in enumerate(w for _ in range(12) for w in (["new", "york"] if rng.random() < 0.4 else [f"w{rng.integers(30)}"]))]
    tokens = spark.createDataFrame(rows, "doc_id long, chunk_no int, pos int, word string, z int")
    for deal in (250_000, 100):
        monkeypatch.setattr(baselines, "DEAL", deal)
        found = {(r["v"], r["w"]) for r in baselines.posthoc_round(tokens, n_perm=20).collect()}
        assert ("new", "york") in found and len(found) <= 3

def test_intrusion_answers(spark):
    view = spark.createDataFrame([(k, "phrase", r + 1, f"p{k}{r}", 9) for k in range(3) for r in range(5)], "k int, kind string, rank int, text string, score long")
    q = evaluate.intrusion_questions(view, 12)
    assert q.count() == 48 and q.where("is_intruder").count() == 12
    units = spark.createDataFrame([(f"d{k}{i}", f"p{k}{r}") for k in range(3) for i in range(4) for r in range(5)], "unit string, item string")
    got = evaluate.intrusion_score(q, evaluate.simulated_answers(q, units, "r")).first()
    assert got["answered"] == got["correct"] == 12


@pytest.mark.parametrize("options", [{"n_topics": "auto", "k_max": 4}, {"optimise_every": 1}, {"inner_sweeps": 2}, {}])
def test_the_way_counts_travel_changes_nothing(spark, planted, monkeypatch, options):
    """Broadcast or joined block by block: the same topics, priors and traces."""
    got = []
    for cells in (topics.SHIP_CELLS, 0):
        monkeypatch.setattr(topics, "SHIP_CELLS", cells)
        m = topics.fit(planted, **{"n_topics": 3, "sweeps": 3, "doc_prior": 0.5, "partitions": 3, "trace_every": 1} | options)
        got.append(({(r.doc_id, r.g, r.z) for r in m.state.collect()}, m.doc_prior.tolist(), m.word_prior, m.trace))
    assert got[0][:1] == got[1][:1] and np.allclose(got[0][1], got[1][1]) and math.isclose(got[0][2], got[1][2])
    assert all(math.isclose(a["perplexity"], b["perplexity"]) for a, b in zip(got[0][3], got[1][3], strict=True))


def test_blocks_follow_the_size(spark, planted, monkeypatch):
    """More blocks where words times topics would be too many for one, and no word lost."""
    monkeypatch.setattr(topics, "BLOCK_CELLS", 500)
    m = topics.fit(planted, 3, sweeps=2, doc_prior=0.5, partitions=1)
    assert m.state.count() == planted.count()
    assert topics.fit(planted.limit(0), 3, sweeps=2).state.count() == 0


def test_snapshot_has_no_other_options(spark):
    rows = spark.createDataFrame([(1, 0, ["a"]), (1, 1, ["b", "c"])], "doc_id long, g int, words array<string>")
    for options in ({"n_topics": "auto"}, {"optimise_every": 1}, {"trace_every": 1}, {"inner_sweeps": 2}):
        with pytest.raises(ValueError, match="snapshot"):
            topics.fit(rows, **{"n_topics": 2, "sweeps": 1, "seed": 1, "mode": "snapshot"} | options)


def test_long_cliques_keep_their_weights(spark):
    """The product over hundreds of words leaves the range of numbers; its logarithm does not."""
    rng = np.random.default_rng(2)
    rows = [(d, g, [f"t{d % 2}w{rng.integers(3)}" for _ in range(400 if g == 0 else 1)]) for d in range(20) for g in range(8)]
    df = spark.createDataFrame(rows, "doc_id long, g int, words array<string>")
    for mode in ("exact", "partitioned"):
        m = topics.fit(df, 2, sweeps=8, doc_prior=0.1, mode=mode, partitions=2)
        truth = df.select("doc_id").distinct().withColumn("block", (F.col("doc_id") % 2).cast("string"))
        assert evaluate.agreement(evaluate.dominant_topic(m.state), truth, "block").first()["purity"] > 0.9


def test_held_out_trace_is_the_measure(spark, planted):
    """The trace's held-out perplexity is that of evaluate.perplexity on the last state, and training alone is what is counted."""
    train, held = planted.where("g % 5 <> 0"), planted.where("g % 5 = 0").unionByName(spark.createDataFrame([(0, 99, ["never"])], planted.schema))
    m = topics.fit(train, 3, sweeps=4, doc_prior=0.5, partitions=2, trace_every=4, held=held)
    want = evaluate.perplexity(m.state, held, 3, 0.5, 0.01).first()
    assert m.trace[-1]["held_tokens"] == want["tokens"] and math.isclose(m.trace[-1]["held_perplexity"], want["perplexity"], rel_tol=1e-9)
    assert m.trace[-1]["held_perplexity"] < m.trace[0]["held_perplexity"]


def test_digamma(spark):
    """Against differences that are finite sums."""
    rows = spark.createDataFrame([(0.01, 1), (0.01, 50), (0.5, 7), (3.0, 200)], "a double, n int")
    for r in rows.select("a", "n", (topics.digamma(F.col("a") + F.col("n")) - topics.digamma(F.col("a"))).alias("d")).collect():
        assert math.isclose(r["d"], sum(1 / (r["a"] + i) for i in range(r["n"])), rel_tol=1e-9)


def test_old_sweeps_are_deleted(spark, planted, tmp_path, monkeypatch):
    """However many sweeps, the shared folder keeps one generation of the documents."""
    from phraseworks.sources import io

    monkeypatch.setattr(io, "shared_folder", lambda _: f"file://{tmp_path}")
    topics.fit(planted, 3, sweeps=4, doc_prior=0.5, partitions=2)
    assert len([p for p in tmp_path.iterdir() if p.name.startswith("sweep-")]) == 1
    assert not [p for p in tmp_path.iterdir() if p.name.startswith("counts-")]


def test_variational_reads_everything(spark, monkeypatch):
    """Whole batches, and a vocabulary of all words however many."""
    from pyspark.ml import clustering, feature

    asked = {}
    for kind, name in ((clustering.LDA, "subsamplingRate"), (feature.CountVectorizer, "vocabSize")):
        monkeypatch.setattr(kind, "fit", lambda self, df, f=kind.fit, name=name: (asked.update({name: self.getOrDefault(name)}), f(self, df))[1])
    chunks = spark.createDataFrame([(i, [f"w{i}", "a"]) for i in range(20)], "doc_id long, toks array<string>")
    assert baselines.lda_variational(chunks, 2, 1).count() == 20
    assert asked["subsamplingRate"] == 1.0 and asked["vocabSize"] == 21


def test_snapshot_sweep_moves_no_token_rows_while_tables_are_small(spark, tmp_path):
    """Cliques meet their words' and documents' counts where they are; only those of several words are brought together."""
    rows = [(i % 40, i // 40, [f"w{i % 17}"] if i % 9 else [f"w{i % 5}", f"w{i % 7}"], i % 3) for i in range(800)]
    spark.createDataFrame(rows, "doc_id long, g int, words array<string>, z int").write.parquet(f"{tmp_path}/state")
    state = spark.read.parquet(f"{tmp_path}/state")
    swept = topics.snapshot_sweep(state, 3, 1)
    assert swept._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning") <= 1
    assert {(r["doc_id"], r["g"], tuple(r["words"])) for r in swept.collect()} == {(d, g, tuple(w)) for d, g, w, _ in rows}


def test_pitman_yor_blocks_seat_as_one_task_would(spark):
    """Customers counted from the phrases, and those a block keeps while it sweeps, are those of seating word by word."""
    rng = np.random.default_rng(5)
    docs = [(rng.zipf(1.4, n) % 20).tolist() for n in rng.integers(2, 40, 30)] + [[1, 2] * 60]
    rows = [(d, 0, [f"w{w}" for w in ids]) for d, ids in enumerate(docs)]
    chunks = spark.createDataFrame(rows, "doc_id long, chunk_no int, toks array<string>")
    out = baselines.pitman_yor_phrases(chunks, n_topics=2, sweeps=2, partitions=3, stay=0.6)
    assert out.agg(F.sum("len")).first()[0] == sum(map(len, docs)) and out.agg(F.max("len")).first()[0] > 2
    ints = lambda lists: pa.array(lists, pa.list_(pa.int32()))
    start = pa.table({"block": pa.array([0] * len(docs), pa.int32()), "doc_id": range(len(docs)), "ids": ints(docs), "inner": ints([[0] + [1] * (len(d) - 1) for d in docs]), "z": ints([rng.integers(0, 2, len(d)) for d in docs]), "x": ints([[0] * len(d) for d in docs])})
    v = len({w for d in docs for w in d})
    seats = []

    class Kept(baselines.Seats):
        def __init__(self, *args):
            super().__init__(*args)
            seats.append((self, args[0]))

    def seated(state):
        count = {}
        for r in state.to_pylist():
            own = ()
            for i, w in enumerate(r["ids"]):
                context = own = (*own, r["ids"][i - 1]) if r["x"][i] else (r["z"][i],)
                while True:
                    here = count.setdefault(context, {})
                    here[w] = here.get(w, 0) + 1
                    if not context or here[w] > 1:
                        break
                    context = context[:-1]
        return count

    def prob(count, context, w):
        below = prob(count, context[:-1], w) if context else 1 / v
        here = count.get(context)
        n = sum(here.values()) if here else 0
        return max(here.get(w, 0) - 0.5, 0) / (1 + n) + (1 + 0.5 * len(here)) / (1 + n) * below if here else below

    sampler, baselines.Seats = baselines.Seats, Kept
    try:
        for sweep in range(3):
            given = baselines._pitman_yor_counts(spark.createDataFrame(start))
            table = given.toArrow()
            heads = [[r for r in table.to_pylist() if r["k"] == k and r["depth"] == 0] for k in range(2)]
            assert sum(r["n"] for r in table.to_pylist()) == sum(m for c, h in seated(start).items() if c for m in h.values())
            sums, sizes = np.array([sum(r["n"] for r in h) for h in heads]), np.array([len(h) for h in heads])
            start = baselines._pitman_yor_sweep(sums, sizes, 0.5, 1.0, 0.5, 0.6, v, 7, sweep)((pa.scalar(0),), start, table)
    finally:
        baselines.Seats = sampler
    last, words = seats[-1]
    count, at = seated(start), {s: divmod(key, last.size) for key, s in last.edges.items()}

    def path(s):
        context, w = (at[s][0], at[s][1]) if s in at else divmod(s - last.k, last.size)
        return (*(path(context) if context >= last.k else (context,)), int(words[w]))

    kept = {path(s): int(last.n[s]) for s in range(last.k, last.used) if last.n[s]}
    assert kept == {(*c, w): m for c, h in count.items() if c for w, m in h.items()} and max(map(len, kept)) > 4
    every = np.arange(last.size)
    heads = last.heads(every)
    np.testing.assert_allclose(heads, [[prob(count, (k,), w) for k in range(2)] for w in words.tolist()])
    for s in range(last.k, last.used, 5):
        want = [prob(count, path(s), w) for w in words.tolist()]
        np.testing.assert_allclose(last.behind(np.full(last.size, s), every, heads), want)
        np.testing.assert_allclose(last.behind(np.full(1, s), every[:1], heads[:1]), want[:1])


def test_pitman_yor_long_phrases(spark):
    """A phrase may be longer than Python's stack is deep."""
    rows = [(d, 0, ["run"] * n) for d, n in enumerate([3000, 5, 2500, 1])]
    out = baselines.pitman_yor_phrases(spark.createDataFrame(rows, "doc_id long, chunk_no int, toks array<string>"), n_topics=2, sweeps=2, stay=0.9999)
    assert {r["doc_id"]: r["n"] for r in out.groupBy("doc_id").agg(F.sum("len").alias("n")).collect()} == {0: 3000, 1: 5, 2: 2500, 3: 1}
    assert out.agg(F.max("len")).first()[0] > 1000
    assert out.where(F.size(F.split("phrase", " ")) != F.col("len")).count() == 0
