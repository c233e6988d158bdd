"""Measures: perplexity, intrusion, coherence, ratings, conformity, agreement, corpus statistics and support curves."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.io import settle
from . import topics


def corpus_stats(chunks: DataFrame, by: str = "lang") -> DataFrame:
    """by, docs, uniq_words, tokens."""
    return chunks.select(by, "doc_id", F.explode("toks").alias("word")).groupBy(by).agg(F.count_distinct("doc_id").alias("docs"), F.count_distinct("word").alias("uniq_words"), F.count("*").alias("tokens"))


def held_out(doc_id: Column) -> Column:
    """One document in eight, by the first digit of its id's md5."""
    return F.substring(F.md5(doc_id.cast("string")), 1, 1).isin("0", "1")


def perplexity(state: DataFrame, scored: DataFrame, n_topics: int, doc_prior: float = 0.5, word_prior: float = 0.01) -> DataFrame:
    """tokens, bits, perplexity of the cliques ``scored`` (doc_id, words) under the model that ``state``'s counts define. Documents
    without state have the prior's topic shares; a word the model has not seen shares one extra vocabulary place."""
    word_topic, doc_topic, topic_total = topics.counts(state)
    vectors = topics._vectors(word_topic, "word", n_topics, "n_word")
    v = vectors.count()
    totals = {r["k"]: r["cnt"] for r in topic_total.collect()}  # n_topics numbers
    docs = topics._vectors(doc_topic, "doc_id", n_topics, "n_doc")
    tokens = scored.select("doc_id", F.explode("words").alias("word")).groupBy("doc_id", "word").agg(F.count("*").alias("m"))
    joined = tokens.join(vectors, "word", "left").join(docs, "doc_id", "left")
    p = F.lit(0.0)
    size = sum((F.coalesce(F.col("n_doc")[k], F.lit(0)) for k in range(n_topics)), F.lit(0))
    for k in range(n_topics):
        th = (F.coalesce(F.col("n_doc")[k], F.lit(0)) + doc_prior) / (size + doc_prior * n_topics)
        ph = (F.coalesce(F.col("n_word")[k], F.lit(0)) + word_prior) / F.lit(totals.get(k, 0) + word_prior * (v + 1))
        p = p + th * ph
    out = joined.select("m", (F.col("m") * F.log(p)).alias("x")).agg(F.sum("m").alias("tokens"), F.sum("x").alias("x"))
    return out.select("tokens", (-F.col("x") / F.col("tokens") / F.log(F.lit(2.0))).alias("bits"), F.exp(-F.col("x") / F.col("tokens")).alias("perplexity"))


def held_phrase(doc_id: Column, g: Column) -> Column:
    """One phrase instance in sixteen, by the md5 of its place."""
    return F.substring(F.md5(F.concat_ws("|", doc_id.cast("string"), g.cast("string"))), 1, 1) == "0"


def completion(state: DataFrame, n_topics: int, doc_prior: float = 0.5, word_prior: float = 0.01, sweeps: int = 6) -> DataFrame:
    """tokens, bits, perplexity of held-out documents: word distributions come from the other documents, each held-out document's
    topic shares from its cliques of even number, and its cliques of odd number are scored. Words unseen in training share the
    smoothing of one place."""
    out = held_out(F.col("doc_id"))
    train, test = state.where(~out), state.where(out)
    phis = topics.phi(train, n_topics, word_prior)
    thetas = topics.infer(test.where("g % 2 = 0"), phis, n_topics, sweeps, doc_prior)
    totals = {r["k"]: r["cnt"] for r in topics.counts(train)[2].collect()}  # n_topics numbers
    tokens = test.where("g % 2 = 1").select("doc_id", F.explode("words").alias("word")).groupBy("doc_id", "word").agg(F.count("*").alias("m"))
    vectors = phis.groupBy("word").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "phi"))), lambda x: x["phi"]).alias("ph"))
    shares = thetas.groupBy("doc_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "theta"))), lambda x: x["theta"]).alias("th"))
    unseen = F.array(*[F.lit(word_prior / (totals.get(k, 0) + word_prior)) for k in range(n_topics)])
    even = F.array(*[F.lit(1.0 / n_topics)] * n_topics)
    p = F.aggregate(F.zip_with(F.coalesce("th", even), F.coalesce("ph", unseen), lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
    x = tokens.join(vectors, "word", "left").join(shares, "doc_id", "left").agg(F.sum("m").alias("tokens"), F.sum(F.col("m") * F.log(p)).alias("x"))
    return x.select("tokens", (-F.col("x") / F.col("tokens") / F.log(F.lit(2.0))).alias("bits"), F.exp(-F.col("x") / F.col("tokens")).alias("perplexity"))


def intrusion_questions(view: DataFrame, n_questions: int = 20, seed: int = 7) -> DataFrame:
    """question, option, phrase, is_intruder: three phrases of one topic's list and one of another's, chosen and shuffled by md5."""
    mark = lambda *cols: F.md5(F.concat_ws("|", F.lit(str(seed)), *[c.cast("string") for c in cols]))
    listed = view.where("kind = 'phrase'").select("k", F.col("text").alias("phrase"))
    ks = listed.groupBy("k").agg(F.count("*").alias("n")).where("n >= 3").select("k")
    q = ks.sparkSession.range(n_questions).select(F.col("id").cast("int").alias("question"))
    pick = Window.partitionBy("question").orderBy("mark", "k")
    # a row for each question and topic, then three and one phrases: sizes set by parameters
    homes = q.crossJoin(ks).withColumn("mark", mark(F.col("question"), F.col("k"))).withColumn("r", F.row_number().over(pick)).where("r <= 2")
    options = homes.join(listed, "k").withColumn("m", mark(F.col("question"), F.col("k"), F.col("phrase"))).withColumn("at", F.row_number().over(Window.partitionBy("question", "r").orderBy("m", "phrase"))).where("(r = 1 and at <= 3) or (r = 2 and at = 1)")
    order = Window.partitionBy("question").orderBy("m", "phrase", "r")
    return options.select("question", F.row_number().over(order).alias("option"), "phrase", (F.col("r") == 2).alias("is_intruder"))


def pair_counts(units: DataFrame, items: DataFrame) -> DataFrame:
    """a, b, both, n_a, n_b, n: units (unit, item) that hold two items of one list (grp, item); the lists are small, so only their
    items' rows are paired, within a unit and list."""
    n = units.select("unit").distinct().agg(F.count("*").alias("n"))
    held = units.join(items.select("item").distinct(), "item").distinct()
    singles = held.groupBy("item").agg(F.count("*").alias("c"))
    pairs = items.select("grp", F.col("item").alias("a")).join(items.select("grp", F.col("item").alias("b")), "grp").where("a < b")
    left, right = held.select("unit", F.col("item").alias("a")), held.select("unit", F.col("item").alias("b"))
    wanted = pairs.select("a", "b").distinct()
    both = left.join(wanted, "a").join(right, ["unit", "b"]).groupBy("a", "b").agg(F.count("*").alias("both"))
    sa, sb = singles.select(F.col("item").alias("a"), F.col("c").alias("n_a")), singles.select(F.col("item").alias("b"), F.col("c").alias("n_b"))
    return pairs.join(both, ["a", "b"], "left").join(sa, "a", "left").join(sb, "b", "left").crossJoin(n).select("grp", "a", "b", F.coalesce("both", F.lit(0)).alias("both"), F.coalesce("n_a", F.lit(0)).alias("n_a"), F.coalesce("n_b", F.lit(0)).alias("n_b"), "n")


def coherence(view: DataFrame, units: DataFrame, kind: str = "npmi", item_kind: str = "word") -> DataFrame:
    """k, coherence: mean over pairs of a topic's listed items, by co-occurrence in units (unit, item). Pairs that never meet
    count -1 ('npmi') or ln(1 / n_b) ('umass')."""
    items = view.where(F.col("kind") == item_kind).select(F.col("k").alias("grp"), F.col("text").alias("item"))
    pairs = pair_counts(units, items)
    joint = F.col("both") / F.col("n")
    npmi = F.when(F.col("both") == 0, -1.0).when(F.col("both") == F.col("n"), 1.0).otherwise(F.log(joint / (F.col("n_a") / F.col("n") * F.col("n_b") / F.col("n"))) / -F.log(joint))
    umass = F.log((F.col("both") + 1) / F.greatest("n_b", F.lit(1)))
    return pairs.groupBy(F.col("grp").alias("k")).agg(F.avg(npmi if kind == "npmi" else umass).alias("coherence"))


def simulated_answers(questions: DataFrame, units: DataFrame, rater: str, margin: float = 0.0) -> DataFrame:
    """question, rater, choice: the option that co-occurs least with the other three (mean npmi over units); null where the two
    lowest are within the margin."""
    items = questions.select(F.col("question").alias("grp"), F.col("phrase").alias("item"))
    p = pair_counts(units, items)
    joint = F.col("both") / F.col("n")
    npmi = F.when(F.col("both") == 0, -1.0).when(F.col("both") == F.col("n"), 1.0).otherwise(F.log(joint / (F.col("n_a") * F.col("n_b") / F.col("n") / F.col("n"))) / -F.log(joint))
    sides = p.select("grp", F.col("a").alias("item"), npmi.alias("s")).unionByName(p.select("grp", F.col("b").alias("item"), npmi.alias("s")))
    # rounded, so that equal means are equal in whatever order their terms were added
    means = sides.groupBy("grp", "item").agg(F.round(F.avg("s"), 9).alias("s")).join(questions.select(F.col("question").alias("grp"), F.col("phrase").alias("item"), "option"), ["grp", "item"])
    low = means.groupBy("grp").agg(F.array_sort(F.collect_list(F.struct("s", "option"))).alias("o"))
    return low.select(F.col("grp").alias("question"), F.lit(rater).alias("rater"), F.when(F.get("o", F.lit(1))["s"] - F.get("o", F.lit(0))["s"] > margin, F.get("o", F.lit(0))["option"]).alias("choice"))


def intrusion_score(questions: DataFrame, answers: DataFrame) -> DataFrame:
    """rater, answered, correct: abstentions (null choices) are neither."""
    truth = questions.where("is_intruder").select("question", F.col("option").alias("right"))
    return answers.join(truth, "question").groupBy("rater").agg(F.count("choice").alias("answered"), F.sum(F.coalesce((F.col("choice") == F.col("right")).cast("int"), F.lit(0))).alias("correct"))


def zscore(ratings: DataFrame) -> DataFrame:
    """method, property, z: each rater's ratings of a property standardised, then averaged."""
    w = Window.partitionBy("rater", "property")
    sd = F.stddev_pop("rating").over(w)
    return ratings.withColumn("s", F.when(sd > 0, (F.col("rating") - F.avg("rating").over(w)) / sd).otherwise(0.0)).groupBy("method", "property").agg(F.avg("s").alias("z"))


def proxy_ratings(view: DataFrame, docs: DataFrame, raters: int = 5, item_kind: str = "word") -> DataFrame:
    """rater, method, property, rating 1..10: raters are hash folds of the corpus, their judgement the npmi of the lists there.
    view has a column method; docs is (doc_id, item)."""
    fold = F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 4), 16, 10).cast("int") % raters
    items = view.where(F.col("kind") == item_kind).select(F.concat_ws("|", "method", "k").alias("grp"), F.col("text").alias("item"))
    out = None
    for r in range(raters):
        pairs = pair_counts(docs.where(fold == r).select(F.col("doc_id").alias("unit"), "item"), items)
        joint = F.col("both") / F.col("n")
        npmi = F.when(F.col("both") == 0, -1.0).when(F.col("both") == F.col("n"), 1.0).otherwise(F.log(joint / (F.col("n_a") * F.col("n_b") / F.col("n") / F.col("n"))) / -F.log(joint))
        one = pairs.groupBy("grp").agg(F.avg(npmi).alias("v")).select(F.lit(r).alias("rater"), F.substring_index("grp", "|", 1).alias("method"), F.lit("coherence").alias("property"), (1 + 9 * (F.col("v") + 1) / 2).alias("rating"))
        out = one if out is None else out.unionByName(one)
    return out


def percent_ranks(rows: DataFrame, value: str, name: str) -> DataFrame:
    """rows with the share of the other rows whose value is smaller, by ranges of the sorted values: no task holds all rows."""
    from ..functions.text import dense_ids

    placed = dense_ids(rows, F.col(value), name="_place")
    first = placed.groupBy(F.col(value).alias("_value")).agg(F.min("_place").alias("_first"))
    n = rows.agg(F.count("*").alias("_all"))
    joined = placed.join(first, F.col(value) == F.col("_value")).crossJoin(n)  # one row on the right
    return joined.withColumn(name, F.when(F.col("_all") > 1, F.col("_first") / (F.col("_all") - 1)).otherwise(0.0)).drop("_place", "_value", "_first", "_all")


def phrase_quality(scores: DataFrame, parts: DataFrame, labels: DataFrame) -> DataFrame:
    """phrase, quality 1..10: decile of the mean rank of a phrase's significance (phrase, sig) and of its share of instances in
    documents labelled good."""
    from ..functions.text import dense_ids

    inst = parts.where("len > 1").select("doc_id", "phrase").join(labels.select("doc_id", "quality"), "doc_id")
    share = inst.groupBy("phrase").agg(F.avg("quality").alias("good"))
    both = settle(scores.join(share, "phrase"), "quality")
    ranked = percent_ranks(percent_ranks(both, "sig", "r1"), "good", "r2").select("phrase", F.round((F.col("r1") + F.col("r2")) / 2, 9).alias("r"))
    n = both.count()
    size, longer = n // 10, n % 10  # the first ``longer`` tenths hold a row more
    at, border = F.col("at"), longer * (size + 1)
    tenth = F.when(at < border, F.floor(at / (size + 1))).otherwise(F.floor((at - border) / max(1, size)) + longer)
    return dense_ids(ranked, F.col("r"), F.col("phrase"), name="at").select("phrase", (tenth + 1).cast("int").alias("quality"))


def holders(units: DataFrame, view: DataFrame) -> DataFrame:
    """unit, item: units (unit, item: a word) that hold all words of a listed phrase, in any order."""
    listed = view.where("kind = 'phrase'").select(F.col("text").alias("item")).distinct().select("item", F.array_distinct(F.split("item", " ")).alias("ws"))
    asked = listed.select("item", F.size("ws").alias("n"), F.explode("ws").alias("word"))
    met = units.select("unit", F.col("item").alias("word")).distinct().join(asked, "word")
    return met.groupBy("unit", "item", "n").agg(F.count("*").alias("have")).where("have = n").select("unit", "item")


def proxy_qualities(view: DataFrame, chunks: DataFrame, raters: int = 5, longest: int = 6) -> DataFrame:
    """rater, method, property, rating 1..10 of each topic's phrase list: raters are hash folds of the corpus, their judgement how
    often the rarest word of a phrase stands in the phrase, as written, where it stands at all. view has a column method."""
    from .mining import ngrams_of

    fold = (F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 4), 16, 10).cast("int") % raters).alias("rater")
    listed = view.where("kind = 'phrase'").select("method", "k", F.col("text").alias("phrase"))
    wanted = listed.select("phrase").distinct().select("phrase", F.split("phrase", " ").alias("ws"))
    grams = chunks.select(fold, F.explode(F.flatten(F.array(*[ngrams_of(F.col("toks"), n) for n in range(1, longest + 1)]))).alias("gram"))
    needed = wanted.select(F.col("phrase").alias("gram")).union(wanted.select(F.explode("ws").alias("gram"))).distinct()
    found = settle(grams.join(needed, "gram", "left_semi").groupBy("rater", "gram").agg(F.count("*").alias("c")), "phrase-counts")
    folds = view.sparkSession.range(raters).select(F.col("id").cast("int").alias("rater"))
    words = wanted.crossJoin(folds).select("rater", "phrase", F.explode("ws").alias("gram")).join(found, ["rater", "gram"], "left")  # as many folds as asked for
    rare = words.groupBy("rater", "phrase").agg(F.min(F.coalesce("c", F.lit(0))).alias("least"))
    rated = rare.join(found.select("rater", F.col("gram").alias("phrase"), "c"), ["rater", "phrase"], "left").select("rater", "phrase", F.when(F.col("least") > 0, F.least(F.lit(1.0), F.coalesce("c", F.lit(0)) / F.col("least"))).otherwise(0.0).alias("share"))
    return listed.join(rated, "phrase").groupBy("rater", "method", "k").agg(F.avg("share").alias("v")).select("rater", "method", F.lit("quality").alias("property"), (1 + 9 * F.col("v")).alias("rating"))


def draws(parts: DataFrame) -> DataFrame:
    """model, draws: topic draws a sweep of the clique model (instances) and of the word model (tokens)."""
    one = parts.agg(F.count("*").alias("cliques"), F.sum("len").alias("words"))
    return one.select(F.expr("stack(2, 'clique', cliques, 'word', words) as (model, draws)"))


def conformity(tokens: DataFrame, parts: DataFrame) -> DataFrame:
    """phrases, same_topic, share: multi-word instances whose words a word-level model (doc_id, chunk_no, pos, z) gives one topic."""
    inst = parts.where("len > 1").select("doc_id", "chunk_no", "g", F.explode(F.sequence(F.col("start"), F.col("start") + F.col("len") - 1)).alias("pos"))
    per = inst.join(tokens.select("doc_id", "chunk_no", "pos", "z"), ["doc_id", "chunk_no", "pos"]).groupBy("doc_id", "g").agg(F.count_distinct("z").alias("t"))
    return per.agg(F.count("*").alias("phrases"), F.sum((F.col("t") == 1).cast("long")).alias("same_topic")).withColumn("share", F.col("same_topic") / F.col("phrases"))


def agreement(assigned: DataFrame, truth: DataFrame, key: str) -> DataFrame:
    """purity, nmi of dominant topics (doc_id, k) against truth (doc_id, key)."""
    cells = assigned.join(truth, "doc_id").groupBy("k", key).agg(F.count("*").alias("c"))
    rows = cells.withColumn("nk", F.sum("c").over(Window.partitionBy("k"))).withColumn("nt", F.sum("c").over(Window.partitionBy(key))).withColumn("best", F.max("c").over(Window.partitionBy("k")))
    n = cells.agg(F.sum("c").alias("n"))
    full = rows.crossJoin(n)  # one row on the right
    mi = F.sum(F.col("c") / F.col("n") * F.log(F.col("c") * F.col("n") / (F.col("nk") * F.col("nt"))))
    hk = F.sum(-F.col("c") / F.col("n") * F.log(F.col("nk") / F.col("n")))
    ht = F.sum(-F.col("c") / F.col("n") * F.log(F.col("nt") / F.col("n")))
    out = full.agg(mi.alias("mi"), hk.alias("hk"), ht.alias("ht"), F.sum(F.col("best") * F.col("c") / F.col("nk") / F.col("n")).alias("purity"))
    return out.select("purity", F.when(F.col("hk") + F.col("ht") > 0, 2 * F.col("mi") / (F.col("hk") + F.col("ht"))).otherwise(0.0).alias("nmi"))


def dominant_topic(state: DataFrame) -> DataFrame:
    """doc_id, k: the topic with the most tokens, ties to the smaller number."""
    rows = topics.counts(state)[1]
    return rows.groupBy("doc_id").agg(F.max_by("k", F.struct("cnt", -F.col("k"))).alias("k"))


def topic_agreement(state: DataFrame, docs: DataFrame, key: str = "lang") -> DataFrame:
    """key, k, docs."""
    return dominant_topic(state).join(docs.select("doc_id", key), "doc_id").groupBy(key, "k").agg(F.count("*").alias("docs"))


def support_curve(counts: DataFrame, truth: DataFrame, supports: list[int]) -> DataFrame:
    """support, found, right, precision, recall of the phrases (n > 1) at each support against true phrases (phrase)."""
    levels = counts.sparkSession.createDataFrame([(s,) for s in supports], "support long")
    t = truth.select("phrase").distinct().withColumn("hit", F.lit(1))
    total = t.agg(F.count("*").alias("total"))
    rows = counts.where("n > 1").join(t, "phrase", "left").join(F.broadcast(levels), F.col("cnt") >= F.col("support"))  # as many levels as asked for
    out = rows.groupBy("support").agg(F.count("*").alias("found"), F.coalesce(F.sum("hit"), F.lit(0)).alias("right")).crossJoin(total)
    return out.select("support", "found", "right", (F.col("right") / F.col("found")).alias("precision"), (F.col("right") / F.col("total")).alias("recall"))


