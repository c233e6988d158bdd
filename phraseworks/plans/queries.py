"""Registered queries: each is a function of (spark, sf_dir), most with DuckDB SQL to hold it against."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import sqlsurface, text
from ..functions.stem import stem_vocabulary
from ..operators import baselines, evaluate, mining, packed, rank, relational, segment, topics
from ..sources.io import scan, settle
from . import methods, pipeline, workloads
from .oracles import DOC_PRIOR, K, LONGEST, SUPPORT, THRESHOLD, WORD_PRIOR, sql, unit

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(oracle: str | None = None) -> Callable[[Query], Query]:
    def register(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if oracle:
            SQL[f.__name__] = oracle
        return f

    return register


def _stages(spark, d, **options):
    """Phrases of up to LONGEST words, as the SQL counts them."""
    return pipeline.stages_of(spark, d, LONGEST, **options)


#: Phrases of any length, for queries without SQL.
_whole = pipeline.stages_of


def _r(c, digits: int = 6):
    return F.round(c, digits)


_SURFACES = """SELECT phrase, arg_min(surface, struct_pack(n := -n, s := surface)) AS surface, sum(n)::BIGINT AS cnt FROM (
    SELECT phrase, array_to_string(all_toks[ats[start + 1] + 1:ats[start + n_words] + 1], ' ') AS surface, count(*) AS n FROM part GROUP BY ALL) GROUP BY phrase"""
_VIEWED = f"""SELECT t.k, 'word' AS kind, t.rank::INT AS rank, s.surface AS text, t.tf AS score FROM topw t JOIN (SELECT word, arg_min(surface, struct_pack(n := -n, s := surface)) AS surface FROM (
        SELECT toks[i] AS word, all_toks[ats[i] + 1] AS surface, count(*) AS n FROM ch, unnest(range(1, len(toks) + 1)) AS x(i) GROUP BY ALL) GROUP BY word) s USING (word)
    UNION ALL SELECT t.k, 'phrase', t.rank::INT, s.surface, t.tf FROM topp t JOIN ({_SURFACES}) s USING (phrase)"""


# --- front end -----------------------------------------------------------------------------------------------------------


@query(sql("SELECT doc_id, chunk_no, (i - 1)::INT AS pos, toks[i] AS word FROM raw, unnest(range(1, len(toks) + 1)) AS t(i)", "raw"))
def chunk_tokens(spark, d):
    return _stages(spark, d).raw.select("doc_id", "chunk_no", F.posexplode("toks").alias("pos", "word"))


@query(r"SELECT doc_id, len(list_filter(string_split_regex(regexp_replace(lower(text), '[^\p{L}\p{N}\s]+|\n', ' ', 'g'), '\s+'), lambda w: w <> ''))::INT AS n_tokens FROM documents WHERE len(list_filter(string_split_regex(regexp_replace(lower(text), '[^\p{L}\p{N}\s]+|\n', ' ', 'g'), '\s+'), lambda w: w <> '')) > 0")
def whole_text_chunks(spark, d):
    return text.chunk(scan(spark, d, "documents", "doc_id", "text"), split=False).select("doc_id", F.size("toks").alias("n_tokens"))


@query(sql("SELECT lang, count(DISTINCT doc_id) AS docs, count(DISTINCT word) AS uniq_words, count(*) AS tokens FROM (SELECT lang, doc_id, unnest(toks) AS word FROM raw) GROUP BY lang", "raw"))
def corpus_stats(spark, d):
    return evaluate.corpus_stats(_stages(spark, d).raw)


@query(sql("SELECT raw.lang, sum(len(raw.toks))::BIGINT AS before, sum(coalesce(len(ch.toks), 0))::BIGINT AS after FROM raw LEFT JOIN ch USING (doc_id, chunk_no) GROUP BY raw.lang", "raw", "ch"))
def stopword_effect(spark, d):
    s = _stages(spark, d)
    kept = s.chunks.groupBy("lang").agg(F.sum(F.size("toks")).alias("after"))
    return s.raw.groupBy("lang").agg(F.sum(F.size("toks")).alias("before")).join(kept, "lang")


@query(sql("SELECT row_number() OVER (ORDER BY cnt DESC, word) - 1 AS word_id, word, cnt FROM (SELECT word, count(*) AS cnt FROM (SELECT unnest(toks) AS word FROM raw) GROUP BY word)", "raw"))
def vocab_ids(spark, d):
    return text.vocabulary(_stages(spark, d).raw)


@query(sql("SELECT ch.doc_id, ch.chunk_no, string_agg(word_id::VARCHAR, ' ' ORDER BY i) AS ids FROM ch, unnest(range(1, len(toks) + 1)) AS t(i) JOIN (SELECT row_number() OVER (ORDER BY cnt DESC, word) - 1 AS word_id, word FROM (SELECT word, count(*) AS cnt FROM (SELECT unnest(toks) AS word FROM ch) GROUP BY word)) v ON v.word = toks[i] GROUP BY ch.doc_id, ch.chunk_no", "ch"))
def encoded_chunks(spark, d):
    s = _stages(spark, d)
    return text.encode(s.chunks, text.vocabulary(s.chunks)).select("doc_id", "chunk_no", F.concat_ws(" ", "ids").alias("ids"))


@query(sql("SELECT count(*) AS chunks, sum(mult)::BIGINT AS copies, max(mult) AS most FROM u", "u"))
def chunk_dedup(spark, d):
    return text.unique_chunks(_stages(spark, d).chunks).agg(F.count("*").alias("chunks"), F.sum("mult").alias("copies"), F.max("mult").alias("most"))


@query(sql("SELECT stem, count(*) AS words, sum(cnt)::BIGINT AS cnt FROM (SELECT word, count(*) AS cnt FROM (SELECT unnest(toks) AS word FROM unstemmed) GROUP BY word) c JOIN stemmed USING (word) GROUP BY stem", "unstemmed", "stemmed", stems=True))
def stems(spark, d):
    return stem_vocabulary(text.vocabulary(_stages(spark, d).chunks)).groupBy("stem").agg(F.count("*").alias("words"), F.sum("cnt").alias("cnt"))


@query(sql("SELECT n, phrase, cnt FROM cnt", "cnt", stems=True))
def stemmed_phrases(spark, d):
    """Phrases of stems: the corpus is stemmed before it is mined."""
    return _stages(spark, d, stem=True).mined.counts


@query(sql(_SURFACES, "part", stems=True))
def stemmed_surface_forms(spark, d):
    """Written forms of phrases that were mined as stems, stop words between their words included."""
    return _stages(spark, d, stem=True).surfaces


@query(sql("SELECT word, arg_min(surface, struct_pack(n := -n, s := surface)) AS surface, sum(n)::BIGINT AS cnt FROM (SELECT toks[i] AS word, all_toks[ats[i] + 1] AS surface, count(*) AS n FROM ch, unnest(range(1, len(toks) + 1)) AS t(i) GROUP BY ALL) GROUP BY word", "ch", stems=True))
def unstemmed_words(spark, d):
    return _stages(spark, d, stem=True).word_surfaces


@query(sql(_VIEWED, "topw", "topp", "part", "ch", stems=True, fitted=True))
def stemmed_topic_view(spark, d):
    """Topics of the stemmed corpus, shown in written forms."""
    s = _stages(spark, d, stem=True)
    return s.view(s.fitted)


# --- mining --------------------------------------------------------------------------------------------------------------


@query(sql("SELECT n, phrase, cnt FROM cnt", "cnt"))
def frequent_phrases(spark, d):
    return _stages(spark, d).mined.counts


@query()
def frequent_phrases_whole(spark, d):
    return _whole(spark, d).mined.counts


@query(sql("SELECT phrase AS word, cnt FROM cnt WHERE n = 1", "cnt"))
def unigram_counts(spark, d):
    return _stages(spark, d).mined.counts.where("n = 1").select(F.col("phrase").alias("word"), "cnt")


@query(sql("""SELECT g.n, count(*) AS candidates, count(*) FILTER (WHERE c >= 10) AS frequent FROM (SELECT n, phrase, count(*) AS c FROM grams WHERE n > 1 GROUP BY n, phrase) g
    JOIN cnt a ON a.phrase = array_to_string(string_split(g.phrase, ' ')[1:g.n - 1], ' ') JOIN cnt b ON b.phrase = array_to_string(string_split(g.phrase, ' ')[2:], ' ') GROUP BY g.n""", "grams", "cnt"))
def level_stats(spark, d):
    stats = _stages(spark, d).mined.stats
    return spark.createDataFrame([(n, c, f) for n, c, f, _ in stats if n > 1], "n int, candidates long, frequent long")


@query(sql("SELECT phrase, count(*) AS cnt, greatest(2, round(0.0001 * any_value(l.l)))::BIGINT AS support FROM grams, l GROUP BY phrase HAVING count(*) >= greatest(2, round(0.0001 * any_value(l.l)))", "grams", "l"))
def frequent_phrases_linear_support(spark, d):
    m = mining.frequent_phrases(_stages(spark, d).chunks, 1e-4, LONGEST, "linear")
    return m.counts.select("phrase", "cnt", F.lit(m.min_support).cast("long").alias("support"))


@query(sql("SELECT n, phrase, count(DISTINCT doc_id) AS docs FROM grams GROUP BY n, phrase HAVING count(DISTINCT doc_id) >= 10", "grams"))
def frequent_phrases_docsupport(spark, d):
    return mining.frequent_phrases(_stages(spark, d).chunks, SUPPORT, LONGEST, support_by="document").counts.withColumnRenamed("cnt", "docs")


@query(sql("SELECT n, count(*) AS grams, sum(c)::BIGINT AS positions FROM (SELECT n, phrase, count(*) AS c FROM grams GROUP BY n, phrase) GROUP BY n", "grams"))
def all_ngrams(spark, d):
    return mining.all_ngrams(_stages(spark, d).chunks, LONGEST).groupBy("n").agg(F.count("*").alias("grams"), F.sum("cnt").alias("positions"))


@query(sql("SELECT n, phrase, cnt FROM cnt WHERE n = 1 OR cnt > 25", "cnt"))
def threshold_pushdown(spark, d):
    return mining.frequent_phrases(_stages(spark, d).chunks, SUPPORT, LONGEST, for_threshold=5.0).counts


@query(sql("SELECT phrase, cnt FROM cnt WHERE n = 2", "cnt"))
def sketch_bigrams(spark, d):
    return mining.sketch_filtered(_stages(spark, d).chunks, SUPPORT)


@query(sql("SELECT n, array_to_string(list_sort(string_split(phrase, ' ')), ' ') AS words, sum(cnt)::BIGINT AS cnt, count(*) AS forms FROM cnt GROUP BY ALL", "cnt"))
def order_free_phrases(spark, d):
    return mining.order_free(_stages(spark, d).mined.counts)


@query()
def similar_phrases(spark, d):
    """Phrases within two edits of each other, in characters; the SQL engine's distance is in bytes, so tests hold this against brute force."""
    return mining.tie_similar(_stages(spark, d).mined.counts, "edit", 2)


_STEMS_OF = "(SELECT phrase, array_to_string(list_transform(string_split(phrase, ' '), lambda w: stem_of[w]), ' ') AS st FROM cnt_unstemmed, (SELECT map(list(word), list(stem)) AS stem_of FROM stemmed))"


@query(sql(f"SELECT a.phrase AS a, b.phrase AS b FROM {_STEMS_OF} a JOIN {_STEMS_OF} b ON a.st = b.st AND a.phrase < b.phrase", "cnt_unstemmed", "stemmed", stems=True))
def same_stems(spark, d):
    """Different phrases whose words have the same stems."""
    return mining.tie_similar(_stages(spark, d).mined.counts, "stem")


@query(sql("""SELECT a.phrase AS a, b.phrase AS b FROM cnt a JOIN cnt b ON a.phrase < b.phrase WHERE a.n > 1 AND b.n > 1
    AND len(list_intersect(list_distinct(string_split(a.phrase, ' ')), list_distinct(string_split(b.phrase, ' ')))) >= 0.6 * len(list_distinct(list_concat(string_split(a.phrase, ' '), string_split(b.phrase, ' '))))""", "cnt"))
def similar_word_sets(spark, d):
    return mining.tie_similar(_stages(spark, d).mined.counts, "jaccard", 0.6)


# --- segmentation --------------------------------------------------------------------------------------------------------


def _bigrams(s):
    ones = s.mined.counts.where("n = 1")
    pairs = s.mined.counts.where("n = 2").select(F.col("phrase").alias("phrase"), F.split("phrase", " ").alias("ws"), F.col("cnt").alias("f12"))
    return pairs.join(ones.select(F.col("phrase").alias("left_p"), F.col("cnt").alias("f1")), F.col("ws")[0] == F.col("left_p")).join(ones.select(F.col("phrase").alias("right_p"), F.col("cnt").alias("f2")), F.col("ws")[1] == F.col("right_p"))


_PAIRS = "FROM (SELECT string_split(phrase, ' ') AS ws, phrase, cnt AS f12 FROM cnt WHERE n = 2) c JOIN cnt a ON a.phrase = ws[1] JOIN cnt b ON b.phrase = ws[2] CROSS JOIN l"


@query(sql(f"SELECT ws[1] AS left_p, ws[2] AS right_p, f12, round(a.cnt::DOUBLE * b.cnt / l.l, 6) AS mu, round((f12 - a.cnt::DOUBLE * b.cnt / l.l) / sqrt(f12), 6) AS sig {_PAIRS}", "cnt", "l"))
def pair_scores(spark, d):
    s = _stages(spark, d)
    f1, f2, f12 = F.col("f1"), F.col("f2"), F.col("f12")
    return _bigrams(s).select("left_p", "right_p", "f12", _r(segment.expected(f1, f2, s.mined.tokens)).alias("mu"), _r(segment.score(f1, f2, f12, s.mined.tokens)).alias("sig"))


@query(sql(f"""SELECT c.phrase, round((f12 - m) / sqrt(f12), 6) AS std, round((f12 - m) / sqrt(f12 * (1 - f12 / l)), 6) AS binomial_var, round((f12 - m) / sqrt(m), 6) AS null_var
    FROM (SELECT c.phrase, f12, l.l AS l, a.cnt::DOUBLE * b.cnt / l.l AS m {_PAIRS}) c""", "cnt", "l"))
def score_variants(spark, d):
    s = _stages(spark, d)
    n, f1, f2, f12 = s.mined.tokens, F.col("f1"), F.col("f2"), F.col("f12")
    return _bigrams(s).select("phrase", *[_r(segment.score(f1, f2, f12, n, k)).alias(k) for k in ("std", "binomial_var", "null_var")])


@query(sql("""SELECT c.phrase, round((c.cnt - p.cnt::DOUBLE * w3.cnt / l.l) / sqrt(c.cnt), 6) AS sig, round((c.cnt - w1.cnt::DOUBLE / l.l * w2.cnt / l.l * w3.cnt) / sqrt(c.cnt), 6) AS unigram_null
    FROM (SELECT *, string_split(phrase, ' ') AS ws FROM cnt WHERE n = 3) c JOIN cnt p ON p.phrase = ws[1] || ' ' || ws[2] JOIN cnt w1 ON w1.phrase = ws[1] JOIN cnt w2 ON w2.phrase = ws[2] JOIN cnt w3 ON w3.phrase = ws[3] CROSS JOIN l""", "cnt", "l"))
def free_rider_ablation(spark, d):
    """Three-word phrases scored as (two words | last) and against all single words, which lets a common last word ride along."""
    s = _stages(spark, d)
    c, n = s.mined.counts, s.mined.tokens
    rows = c.where("n = 3").select("phrase", F.split("phrase", " ").alias("ws"), F.col("cnt").alias("f"))
    for name, key in (("fp", F.concat_ws(" ", F.slice("ws", 1, 2))), ("w1", F.col("ws")[0]), ("w2", F.col("ws")[1]), ("w3", F.col("ws")[2])):
        rows = rows.join(c.select(F.col("phrase").alias(f"{name}_k"), F.col("cnt").alias(name)), key == F.col(f"{name}_k"))
    free = F.col("w1") / F.lit(float(n)) * F.col("w2") / F.lit(float(n)) * F.col("w3")
    return rows.select("phrase", _r(segment.score(F.col("fp"), F.col("w3"), F.col("f"), n)).alias("sig"), _r(segment.score(F.col("fp"), F.col("w3"), F.col("f"), n, mean=free)).alias("unigram_null"))


@query(sql("SELECT doc_id, chunk_no, g, phrase, n_words FROM part", "part"))
def segment_partition(spark, d):
    return _stages(spark, d).parts.select("doc_id", "chunk_no", "g", "phrase", F.col("len").alias("n_words"))


@query(sql("SELECT array_to_string(u.toks, ' ') AS chunk, u.mult, i::INT AS step, merges[i].a AS left_phrase, merges[i].b AS right_phrase, round(merges[i].s, 6) AS sig FROM seg JOIN u USING (uid), unnest(range(1, len(merges) + 1)) AS t(i)", "seg", "u"))
def segment_trace(spark, d):
    return segment.trace(_stages(spark, d).mined, THRESHOLD).withColumn("sig", _r(F.col("sig")))


@query(sql("SELECT phrase, n_words, cnt FROM bagged", "bagged"))
def bag_of_phrases(spark, d):
    return segment.bag_unique(_stages(spark, d).mined, THRESHOLD)


@query()
def segment_partition_whole(spark, d):
    return _whole(spark, d).parts.select("doc_id", "chunk_no", "g", "phrase", F.col("len").alias("n_words"))


@query()
def bag_of_phrases_whole(spark, d):
    return segment.bag_unique(_whole(spark, d).mined, THRESHOLD)


@query(sql("SELECT c.phrase, c.cnt AS raw_cnt FROM cnt c ANTI JOIN bagged b ON b.phrase = c.phrase WHERE c.n > 1", "cnt", "bagged"))
def rejected_candidates(spark, d):
    s = _stages(spark, d)
    return segment.rejected(s.mined.counts, segment.bag(s.parts))


@query(sql("SELECT count(*) AS chunks, 0::BIGINT AS broken FROM ch", "ch"))
def partition_check(spark, d):
    s = _stages(spark, d)
    broken = segment.check_partition(s.parts, s.chunks).agg(F.count("*").alias("broken"))
    return s.chunks.agg(F.count("*").alias("chunks")).crossJoin(broken)


@query(sql(_SURFACES, "part"))
def surface_forms(spark, d):
    return _stages(spark, d).surfaces


# --- topic model ---------------------------------------------------------------------------------------------------------


@query(sql("SELECT z AS k, count(*) AS cliques, sum(n_words)::BIGINT AS tokens FROM z0 GROUP BY z", "z0"))
def init_topics(spark, d):
    return _stages(spark, d).state.groupBy(F.col("z").alias("k")).agg(F.count("*").alias("cliques"), F.sum(F.size("words")).alias("tokens"))


@query(sql("SELECT word, k, c AS cnt FROM wk", "wk"))
def topic_counts(spark, d):
    return topics.counts(_stages(spark, d).state)[0]


@query(sql("SELECT doc_id, k, round(sum(p), 5) AS expected FROM probs GROUP BY doc_id, k", "probs"))
def clique_conditional(spark, d):
    """Expected cliques of each topic by document: sums of every clique's conditional law."""
    p = topics.probabilities(topics.clique_weights(_stages(spark, d).state, K, DOC_PRIOR, WORD_PRIOR))
    return p.select("doc_id", F.posexplode("probs").alias("k", "p")).groupBy("doc_id", "k").agg(_r(F.sum("p"), 5).alias("expected"))


@query(sql(f"""SELECT doc_id, g, least(count(*) FILTER (WHERE cum <= u), {K - 1})::INT AS z FROM (
    SELECT doc_id, g, sum(p) OVER (PARTITION BY doc_id, g ORDER BY k ROWS UNBOUNDED PRECEDING) AS cum, {unit('doc_id', 'g', sweep=1)} AS u FROM probs) GROUP BY doc_id, g""", "probs"))
def snapshot_sweep_1(spark, d):
    return topics.snapshot_sweep(_stages(spark, d).state, K, 1, doc_prior=DOC_PRIOR, word_prior=WORD_PRIOR).select("doc_id", "g", "z")


@query(sql(f"""SELECT doc_id, g, least(count(*) FILTER (WHERE cum <= u), {K - 1})::INT AS z FROM (
    SELECT doc_id, g, k, sum(p) OVER (PARTITION BY doc_id, g ORDER BY k ROWS UNBOUNDED PRECEDING) / sum(p) OVER (PARTITION BY doc_id, g) AS cum, {unit('doc_id', 'g', sweep=1)} AS u FROM (
        SELECT t.doc_id, t.g, ks.k, ({DOC_PRIOR} + coalesce(a.c, 0) - (t.z = ks.k)::INT) * ({WORD_PRIOR} + coalesce(b.c, 0) - (t.z = ks.k)::INT) / ({WORD_PRIOR} * vv.v + c.c - (t.z = ks.k)::INT) AS p
        FROM (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY chunk_no, pos) - 1 AS g FROM lw) t CROSS JOIN ks CROSS JOIN (SELECT count(DISTINCT word) AS v FROM lw) vv
        JOIN (SELECT z, count(*) AS c FROM lw GROUP BY z) c ON c.z = ks.k
        LEFT JOIN (SELECT doc_id, z, count(*) AS c FROM lw GROUP BY ALL) a ON a.doc_id = t.doc_id AND a.z = ks.k
        LEFT JOIN (SELECT word, z, count(*) AS c FROM lw GROUP BY ALL) b ON b.word = t.word AND b.z = ks.k)) GROUP BY doc_id, g""", "lw", "ks"))
def snapshot_sweep_lda(spark, d):
    state = _stages(spark, d).words.select("doc_id", "g", F.array("word").alias("words"), "z")
    return topics.snapshot_sweep(state, K, 1, doc_prior=DOC_PRIOR, word_prior=WORD_PRIOR).select("doc_id", "g", "z")


@query(sql("SELECT doc_id, g, z FROM z0", "z0", fitted=True))
def snapshot_chain(spark, d):
    """Topics of the clique model after some snapshot sweeps, each from the counts of the one before."""
    return _stages(spark, d).fitted.select("doc_id", "g", "z")


@query(sql("SELECT doc_id, chunk_no, pos, z FROM lw", "lw", fitted=True))
def snapshot_chain_lda(spark, d):
    return _stages(spark, d).fitted_words.select("doc_id", "chunk_no", "pos", "z")


@query(sql(f"SELECT round({WORD_PRIOR} * a.up / (b.v * c.down), 9) AS prior FROM (SELECT sum(1 / ({WORD_PRIOR} + i)) AS up FROM wk, unnest(range(0, c)) AS t(i)) a, v b, (SELECT sum(part) AS down FROM (SELECT sum(1 / (v.v * {WORD_PRIOR} + i)) AS part FROM tk CROSS JOIN v, unnest(range(0, tk.c)) AS t(i) GROUP BY tk.k)) c", "wk", "tk", "v", fitted=True))
def word_prior_fixed_point_step(spark, d):
    return spark.createDataFrame([(topics.word_prior_step(_stages(spark, d).fitted, K, WORD_PRIOR),)], "prior double").select(_r(F.col("prior"), 9).alias("prior"))


@query(sql(f"""SELECT a.k, round({DOC_PRIOR} * a.part / b.part, 6) AS prior FROM
    (SELECT k, sum(1 / ({DOC_PRIOR} + i)) AS part FROM dk, unnest(range(0, c)) AS t(i) GROUP BY k) a,
    (SELECT sum(1 / ({DOC_PRIOR * K} + i)) AS part FROM (SELECT doc_id, sum(c)::BIGINT AS c FROM dk GROUP BY doc_id) s, unnest(range(0, c)) AS t(i)) b""", "dk"))
def prior_fixed_point_step(spark, d):
    return topics.prior_step(_stages(spark, d).state, K, [DOC_PRIOR] * K).select("k", _r(F.col("prior")).alias("prior"))


@query(sql(f"""SELECT round((SELECT sum(lgamma(c + {DOC_PRIOR}) - lgamma({DOC_PRIOR})) FROM dk) + (SELECT sum(lgamma({DOC_PRIOR * K}) - lgamma(c + {DOC_PRIOR * K})) FROM (SELECT sum(c)::BIGINT AS c FROM dk GROUP BY doc_id))
    + (SELECT sum(lgamma(c + {WORD_PRIOR}) - lgamma({WORD_PRIOR})) FROM wk) + (SELECT sum(lgamma(v * {WORD_PRIOR}) - lgamma(c + v * {WORD_PRIOR})) FROM tk, v), 2) AS log_joint""", "dk", "wk", "tk", "v"))
def log_joint(spark, d):
    return topics.log_joint(_stages(spark, d).state, K, DOC_PRIOR, WORD_PRIOR).select(_r(F.col("log_joint"), 2).alias("log_joint"))


@query(sql(f"SELECT t.k, rank::INT AS rank, word, round((tf + {WORD_PRIOR}) / (tk.c + {WORD_PRIOR} * v.v), 6) AS phi FROM topw t JOIN tk ON tk.k = t.k CROSS JOIN v", "topw", "tk", "v", fitted=True))
def phi_top_words(spark, d):
    p = topics.phi(_stages(spark, d).fitted, K, WORD_PRIOR)
    return rank.top(p, 10, F.col("phi"), "word").select("k", "rank", "word", _r(F.col("phi")).alias("phi"))


@query(sql(f"SELECT d.doc_id, ks.k, round((coalesce(dk.c, 0) + {DOC_PRIOR}) / (d.n + {DOC_PRIOR * K}), 6) AS theta FROM (SELECT doc_id, sum(c) AS n FROM dk GROUP BY doc_id) d CROSS JOIN ks LEFT JOIN dk ON dk.doc_id = d.doc_id AND dk.k = ks.k", "dk", "ks", fitted=True))
def theta_docs(spark, d):
    return topics.theta(_stages(spark, d).fitted, K, DOC_PRIOR).select("doc_id", "k", _r(F.col("theta")).alias("theta"))


@query(sql("SELECT phrase, n_words, k, tf FROM tf", "tf", fitted=True))
def topical_frequency(spark, d):
    return rank.topical_frequency(_stages(spark, d).fitted)


_VIEW = "SELECT k, 'word' AS kind, rank::INT AS rank, word AS text, tf AS score FROM topw UNION ALL SELECT k, 'phrase', rank::INT, phrase, tf FROM topp"


@query(sql(_VIEW, "topw", "topp", fitted=True))
def topic_view(spark, d):
    return rank.topic_view(_stages(spark, d).fitted)


@query(sql("""SELECT k, phrase, round(sum(pk * ln(pk / q)), 6) AS kl, round(sum(pk * ln(q / (w / n))), 6) AS mi, round(sum(pk * ln(q / (w / n))) - sum(pk * ln(pk / q)), 6) AS score FROM (
    SELECT p.k, x.phrase, p.tf / s.total AS pk, x.c / sum(x.c) OVER (PARTITION BY x.phrase, p.k) AS unused, x.c / sz.s AS q, e.w::DOUBLE AS w, nn.n::DOUBLE AS n
    FROM (SELECT h.phrase, t.word, count(*) AS c FROM (SELECT DISTINCT doc_id, phrase FROM z0 WHERE phrase IN (SELECT phrase FROM tf WHERE n_words > 1 AND tf >= 5)) h JOIN tok t ON t.doc_id = h.doc_id GROUP BY ALL) x
    JOIN (SELECT h.phrase, count(*) AS s FROM (SELECT DISTINCT doc_id, phrase FROM z0 WHERE phrase IN (SELECT phrase FROM tf WHERE n_words > 1 AND tf >= 5)) h JOIN tok t ON t.doc_id = h.doc_id GROUP BY h.phrase) sz ON sz.phrase = x.phrase
    JOIN wtf p ON p.word = x.word JOIN (SELECT k, sum(tf) AS total FROM wtf GROUP BY k) s ON s.k = p.k
    JOIN (SELECT word, sum(tf) AS w FROM wtf GROUP BY word) e ON e.word = x.word CROSS JOIN (SELECT sum(tf) AS n FROM wtf) nn) GROUP BY k, phrase""", "z0", "tf", "tok", "wtf", fitted=True))
def label_kl(spark, d):
    return rank.label_score(_stages(spark, d).fitted).select("k", "phrase", *[_r(F.col(c)).alias(c) for c in ("kl", "mi", "score")])


@query(sql("""SELECT k, phrase, round(1.0 * s(f1, a1, b1) + 1.0 * s(f2, a2, b2) + 0.5 * s(f3, a3, b3) + 0.25 * s(f4, a4, b4), 6) AS facet_score FROM (
    SELECT *, min(f1) OVER w AS a1, max(f1) OVER w AS b1, min(f2) OVER w AS a2, max(f2) OVER w AS b2, min(f3) OVER w AS a3, max(f3) OVER w AS b3, min(f4) OVER w AS a4, max(f4) OVER w AS b4 FROM (
        SELECT tf.k, tf.phrase, ln(tf) AS f1, tf / sum(tf) OVER (PARTITION BY tf.phrase) AS f2, coalesce(sg.sig, 0.0) AS f3, n_words::DOUBLE AS f4 FROM tf LEFT JOIN (
            SELECT c.phrase, (c.f12 - a.cnt::DOUBLE * b.cnt / l.l) / sqrt(c.f12) AS sig """.replace("s(f1, a1, b1)", "CASE WHEN b1 > a1 THEN (f1 - a1) / (b1 - a1) ELSE 0 END").replace("s(f2, a2, b2)", "CASE WHEN b2 > a2 THEN (f2 - a2) / (b2 - a2) ELSE 0 END").replace("s(f3, a3, b3)", "CASE WHEN b3 > a3 THEN (f3 - a3) / (b3 - a3) ELSE 0 END").replace("s(f4, a4, b4)", "CASE WHEN b4 > a4 THEN (f4 - a4) / (b4 - a4) ELSE 0 END") + _PAIRS + ") sg ON sg.phrase = tf.phrase WHERE n_words > 1) WINDOW w AS (PARTITION BY k))", "tf", "cnt", "l", fitted=True))
def multi_facet_rank(spark, d):
    s = _stages(spark, d)
    sig = _bigrams(s).select("phrase", segment.score(F.col("f1"), F.col("f2"), F.col("f12"), s.mined.tokens).alias("sig"))
    return rank.multi_facet(rank.topical_frequency(s.fitted), sig).withColumn("facet_score", _r(F.col("facet_score")))


@query(sql(f"SELECT phrase, n_words, k, tf FROM (SELECT *, round(-sum(q * ln(q)) OVER (PARTITION BY phrase), 9) AS h FROM (SELECT *, tf / sum(tf) OVER (PARTITION BY phrase) AS q FROM tf)) WHERE h <= round(0.9 * ln({K}), 9)", "tf", fitted=True))
def background_filter(spark, d):
    return rank.drop_background(rank.topical_frequency(_stages(spark, d).fitted), K)


@query(sql("SELECT tf.* FROM tf SEMI JOIN (SELECT unnest(list_concat(w, list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]))) AS phrase FROM (SELECT list_filter(string_split_regex(p, '\\s+'), lambda x: x <> '') AS w FROM (SELECT unnest(string_split_regex(lower(text), '[^\\p{L}\\p{N}\\s]+|\\n')) AS p FROM benchmark))) b ON b.phrase = tf.phrase", "tf", fitted=True))
def candidate_pool(spark, d):
    pool = text.chunk(scan(spark, d, "benchmark"), id_col="item_id").select(F.explode(F.concat("toks", mining.ngrams_of(F.col("toks"), 2))).alias("phrase"))
    return rank.with_candidates(rank.topical_frequency(_stages(spark, d).fitted), pool)


# --- measures ------------------------------------------------------------------------------------------------------------


_TH = f"(coalesce(dk.c, 0) + {DOC_PRIOR}) / (d.n + {DOC_PRIOR * K})"


@query(sql(f"""SELECT sum(m)::BIGINT AS tokens, round(-sum(m * ln(p)) / sum(m) / ln(2), 6) AS bits, round(exp(-sum(m * ln(p)) / sum(m)), 3) AS perplexity FROM (
    SELECT t.doc_id, t.word, any_value(t.m) AS m, sum({_TH} * (coalesce(wk.c, 0) + {WORD_PRIOR}) / (tk.c + {WORD_PRIOR} * (v.v + 1))) AS p
    FROM (SELECT doc_id, word, count(*) AS m FROM tok GROUP BY ALL) t JOIN (SELECT doc_id, sum(c) AS n FROM dk GROUP BY doc_id) d ON d.doc_id = t.doc_id CROSS JOIN v JOIN tk ON true
    LEFT JOIN dk ON dk.doc_id = t.doc_id AND dk.k = tk.k LEFT JOIN wk ON wk.word = t.word AND wk.k = tk.k GROUP BY t.doc_id, t.word)""", "tok", "dk", "wk", "tk", "v", fitted=True))
def perplexity_frozen(spark, d):
    s = _stages(spark, d)
    return evaluate.perplexity(s.fitted, s.cliques, K, DOC_PRIOR, WORD_PRIOR).select("tokens", _r(F.col("bits")).alias("bits"), _r(F.col("perplexity"), 3).alias("perplexity"))


_HELD = "substr(md5(doc_id || '|' || g), 1, 1) = '0'"


@query(sql(f"""SELECT sum(m)::BIGINT AS tokens, round(-sum(m * ln(p)) / sum(m) / ln(2), 6) AS bits, round(exp(-sum(m * ln(p)) / sum(m)), 3) AS perplexity FROM (
    SELECT h.doc_id, h.word, any_value(h.m) AS m, sum((coalesce(a.c, 0) + {DOC_PRIOR}) / (coalesce(n.c, 0) + {DOC_PRIOR * K}) * (coalesce(b.c, 0) + {WORD_PRIOR}) / (t.c + {WORD_PRIOR} * (v.v + 1))) AS p
    FROM (SELECT doc_id, word, count(*) AS m FROM tok WHERE {_HELD} GROUP BY ALL) h CROSS JOIN (SELECT count(DISTINCT word) AS v FROM tok WHERE NOT {_HELD}) v
    CROSS JOIN (SELECT z, count(*) AS c FROM tok WHERE NOT {_HELD} GROUP BY z) t
    LEFT JOIN (SELECT doc_id, z, count(*) AS c FROM tok WHERE NOT {_HELD} GROUP BY ALL) a ON a.doc_id = h.doc_id AND a.z = t.z
    LEFT JOIN (SELECT word, z, count(*) AS c FROM tok WHERE NOT {_HELD} GROUP BY ALL) b ON b.word = h.word AND b.z = t.z
    LEFT JOIN (SELECT doc_id, count(*) AS c FROM tok WHERE NOT {_HELD} GROUP BY doc_id) n ON n.doc_id = h.doc_id GROUP BY h.doc_id, h.word)""", "tok", fitted=True))
def perplexity_held_phrases(spark, d):
    """A sixteenth of every document's phrases, hidden from the counts and scored with the document's other phrases."""
    s = _stages(spark, d)
    held = evaluate.held_phrase(F.col("doc_id"), F.col("g"))
    return evaluate.perplexity(s.fitted.where(~held), s.cliques.where(held), K, DOC_PRIOR, WORD_PRIOR).select("tokens", _r(F.col("bits")).alias("bits"), _r(F.col("perplexity"), 3).alias("perplexity"))


@query()
def perplexity_completion(spark, d):
    """Held-out documents by half: topics from the phrases of even number, scores on those of odd number, for both models."""
    s = _stages(spark, d)
    out = None
    for model, state in (("clique", s.fitted), ("word", s.fitted_words.select("doc_id", "g", F.array("word").alias("words"), "z"))):
        one = evaluate.completion(state, K, DOC_PRIOR, WORD_PRIOR).select(F.lit(model).alias("model"), "*")
        out = one if out is None else out.unionByName(one)
    return out


_QUESTIONS = """SELECT question, row_number() OVER (PARTITION BY question ORDER BY m, phrase, r)::INT AS option, phrase, r = 2 AS is_intruder FROM (
    SELECT q.question, q.r, p.phrase, md5('7|' || q.question || '|' || q.k || '|' || p.phrase) AS m, row_number() OVER (PARTITION BY q.question, q.r ORDER BY md5('7|' || q.question || '|' || q.k || '|' || p.phrase), p.phrase) AS at_
    FROM (SELECT * FROM (SELECT i::INT AS question, k, row_number() OVER (PARTITION BY i ORDER BY md5('7|' || i || '|' || k), k) AS r FROM range(20) AS t(i), (SELECT k FROM topp GROUP BY k HAVING count(*) >= 3)) WHERE r <= 2) q JOIN topp p ON p.k = q.k)
    WHERE (r = 1 AND at_ <= 3) OR (r = 2 AND at_ = 1)"""


@query(sql(_QUESTIONS, "topp", fitted=True))
def intrusion_questions(spark, d):
    return evaluate.intrusion_questions(rank.topic_view(_stages(spark, d).fitted))


def _npmi_sql(items: str, units: str) -> str:
    """grp, a, b, s: how items of one group (grp, item) go together over distinct units (unit, item)."""
    listed = f"(SELECT * FROM {units} x WHERE item IN (SELECT item FROM {items}))"
    return f"""(SELECT grp, a, b, CASE WHEN both_ = 0 THEN -1.0 WHEN both_ = n THEN 1.0 ELSE ln(both_ / n / (na / n * nb / n)) / -ln(both_ / n) END AS s FROM (
        SELECT p.grp, p.a, p.b, coalesce(c.c, 0) AS both_, x.c AS na, y.c AS nb, (SELECT count(DISTINCT unit) FROM {units} z)::DOUBLE AS n FROM (SELECT l.grp, l.item AS a, r.item AS b FROM {items} l JOIN {items} r ON l.grp = r.grp AND l.item < r.item) p
        LEFT JOIN (SELECT h.item AS a, o.item AS b, count(*) AS c FROM {listed} h JOIN {listed} o ON h.unit = o.unit AND h.item < o.item GROUP BY ALL) c ON c.a = p.a AND c.b = p.b
        LEFT JOIN (SELECT item, count(*) AS c FROM {units} z GROUP BY item) x ON x.item = p.a LEFT JOIN (SELECT item, count(*) AS c FROM {units} z GROUP BY item) y ON y.item = p.b))"""


def _rater_sql(rater: str, unit: str, source: str) -> str:
    items, units = f"(SELECT question AS grp, phrase AS item FROM ({_QUESTIONS}) w)", f"(SELECT DISTINCT {unit} AS unit, phrase AS item FROM {source} WHERE n_words > 1)"
    means = f"SELECT m.grp, m.s, o.option, o.is_intruder, row_number() OVER (PARTITION BY m.grp ORDER BY m.s, o.option) AS r, lead(m.s) OVER (PARTITION BY m.grp ORDER BY m.s, o.option) AS next_s FROM (SELECT grp, item, round(avg(s), 9) AS s FROM (SELECT grp, a AS item, s FROM {_npmi_sql(items, units)} UNION ALL SELECT grp, b, s FROM {_npmi_sql(items, units)}) GROUP BY ALL) m JOIN ({_QUESTIONS}) o ON o.question = m.grp AND o.phrase = m.item"
    return f"SELECT '{rater}' AS rater, count(*) FILTER (WHERE next_s > s) AS answered, count(*) FILTER (WHERE next_s > s AND is_intruder) AS correct FROM ({means}) WHERE r = 1"


@query(sql(" UNION ALL ".join((_rater_sql("document", "doc_id::VARCHAR", "part"), _rater_sql("chunk", "doc_id || '|' || chunk_no", "part"), _rater_sql("source", "source", "(SELECT part.*, documents.source FROM part JOIN documents USING (doc_id))"))), "topp", "part", fitted=True))
def intrusion_scores(spark, d):
    s = _stages(spark, d)
    q = evaluate.intrusion_questions(rank.topic_view(s.fitted))
    p = s.parts.where("len > 1")
    units = {"document": p.select(F.col("doc_id").cast("string").alias("unit"), F.col("phrase").alias("item")), "chunk": p.select(F.concat_ws("|", "doc_id", "chunk_no").alias("unit"), F.col("phrase").alias("item")), "source": p.join(s.docs.select("doc_id", "source"), "doc_id").select(F.col("source").alias("unit"), F.col("phrase").alias("item"))}
    answers = None
    for rater, u in units.items():
        a = evaluate.simulated_answers(q, u, rater)
        answers = a if answers is None else answers.unionByName(a)
    return evaluate.intrusion_score(q, answers)


_PAIRED = """(SELECT a.k, a.word AS a, b.word AS b FROM topw a JOIN topw b ON a.k = b.k AND a.word < b.word) p
    LEFT JOIN (SELECT x.word AS a, y.word AS b, count(*) AS both_ FROM (SELECT * FROM dw WHERE word IN (SELECT word FROM topw)) x JOIN (SELECT * FROM dw WHERE word IN (SELECT word FROM topw)) y ON x.doc_id = y.doc_id AND x.word < y.word GROUP BY ALL) c ON c.a = p.a AND c.b = p.b
    JOIN (SELECT word, count(*) AS c FROM dw GROUP BY word) na ON na.word = p.a JOIN (SELECT word, count(*) AS c FROM dw GROUP BY word) nb ON nb.word = p.b CROSS JOIN (SELECT count(DISTINCT doc_id) AS n FROM dw) nn"""


def _doc_words(s):
    return s.chunks.select(F.col("doc_id").alias("unit"), F.explode("toks").alias("item"))


@query(sql(f"SELECT p.k, round(avg(CASE WHEN both_ IS NULL THEN -1.0 WHEN both_ = n THEN 1.0 ELSE ln((both_ / n) / ((na.c / n) * (nb.c / n))) / -ln(both_ / n) END), 6) AS npmi FROM {_PAIRED} GROUP BY p.k", "topw", "dw", fitted=True))
def npmi_coherence(spark, d):
    s = _stages(spark, d)
    return evaluate.coherence(rank.topic_view(s.fitted), _doc_words(s)).select("k", _r(F.col("coherence")).alias("npmi"))


@query(sql(f"SELECT p.k, round(avg(ln((coalesce(both_, 0) + 1) / nb.c)), 6) AS umass FROM {_PAIRED} GROUP BY p.k", "topw", "dw", fitted=True))
def umass_coherence(spark, d):
    s = _stages(spark, d)
    return evaluate.coherence(rank.topic_view(s.fitted), _doc_words(s), "umass").select("k", _r(F.col("coherence")).alias("umass"))


@query("""WITH r AS (SELECT 'r' || (quality % 2) AS rater, 'm' || (doc_id % 3) AS method, 'quality' AS property, (1 + doc_id % 10)::DOUBLE AS rating FROM labels)
SELECT method, property, round(avg((rating - m) / s), 6) AS z FROM (SELECT *, avg(rating) OVER (PARTITION BY rater, property) AS m, stddev_pop(rating) OVER (PARTITION BY rater, property) AS s FROM r) GROUP BY method, property""")
def rating_zscores(spark, d):
    """Standardised ratings, on ratings made from the label table's numbers."""
    r = scan(spark, d, "labels").select(F.concat(F.lit("r"), F.col("quality") % 2).alias("rater"), F.concat(F.lit("m"), F.col("doc_id") % 3).alias("method"), F.lit("quality").alias("property"), (1 + F.col("doc_id") % 10).cast("double").alias("rating"))
    return evaluate.zscore(r).select("method", "property", _r(F.col("z")).alias("z"))


_LISTED = "(SELECT 'clique|' || k AS grp, word AS item FROM topw UNION ALL SELECT 'word|' || z, word FROM (SELECT z, word, row_number() OVER (PARTITION BY z ORDER BY count(*) DESC, word) AS r FROM lw GROUP BY z, word) WHERE r <= 10)"
_FOLD = "('0x' || substr(md5(doc_id::VARCHAR), 1, 4))::BIGINT % 5"
_RATED = " UNION ALL ".join(f"SELECT {r} AS rater, split_part(grp, '|', 1) AS method, 1 + 9 * (avg(s) + 1) / 2 AS rating FROM {_npmi_sql(_LISTED, f'(SELECT doc_id AS unit, word AS item FROM dw WHERE {_FOLD} = {r})')} GROUP BY grp" for r in range(5))


@query(sql(f"SELECT method, 'coherence' AS property, round(avg((rating - m) / s), 6) AS z FROM (SELECT *, avg(rating) OVER (PARTITION BY rater) AS m, stddev_pop(rating) OVER (PARTITION BY rater) AS s FROM ({_RATED})) GROUP BY method", "topw", "lw", "dw", fitted=True))
def coherence_zscores(spark, d):
    """The clique model's and the word model's lists, rated by five folds of the corpus."""
    s = _stages(spark, d)
    one = rank.topic_view(s.fitted).withColumn("method", F.lit("clique"))
    two = rank.topic_view(s.fitted_words.select("doc_id", "g", F.array("word").alias("words"), "z")).withColumn("method", F.lit("word"))
    return evaluate.zscore(evaluate.proxy_ratings(one.unionByName(two), s.chunks.select("doc_id", F.explode("toks").alias("item")))).withColumn("z", _r(F.col("z")))


@query(sql(f"""SELECT phrase, ntile(10) OVER (ORDER BY r, phrase)::INT AS quality FROM (SELECT phrase, round((percent_rank() OVER (ORDER BY sig) + percent_rank() OVER (ORDER BY good)) / 2, 9) AS r FROM (
    SELECT c.phrase, round((f12 - a.cnt::DOUBLE * b.cnt / l.l) / sqrt(f12), 9) AS sig {_PAIRS}) JOIN (SELECT phrase, avg(quality) AS good FROM part JOIN labels USING (doc_id) WHERE n_words > 1 GROUP BY phrase) USING (phrase))""", "cnt", "l", "part"))
def phrase_quality(spark, d):
    s = _stages(spark, d)
    sig = _bigrams(s).select("phrase", _r(segment.score(F.col("f1"), F.col("f2"), F.col("f12"), s.mined.tokens), 9).alias("sig"))
    return evaluate.phrase_quality(sig, s.parts, scan(spark, d, "labels"))


@query(sql("SELECT count(*) AS phrases, count(*) FILTER (WHERE t = 1) AS same_topic, round(count(*) FILTER (WHERE t = 1) / count(*), 6) AS share FROM (SELECT p.doc_id, p.g, count(DISTINCT lw.z) AS t FROM part p, unnest(range(0, n_words)) AS o(i) JOIN lw ON lw.doc_id = p.doc_id AND lw.chunk_no = p.chunk_no AND lw.pos = p.start + i WHERE p.n_words > 1 GROUP BY p.doc_id, p.g)", "part", "lw", fitted=True))
def conformity(spark, d):
    s = _stages(spark, d)
    return evaluate.conformity(s.fitted_words, s.parts).withColumn("share", _r(F.col("share")))


@query(sql("SELECT 'clique' AS model, count(*) AS draws FROM part UNION ALL SELECT 'word', sum(n_words)::BIGINT FROM part", "part"))
def draws_per_sweep(spark, d):
    return evaluate.draws(_stages(spark, d).parts)


_TRUTH = "(SELECT DISTINCT array_to_string(w[i:i + 1], ' ') AS phrase FROM (SELECT list_filter(string_split_regex(p, '\\s+'), lambda x: x <> '') AS w FROM (SELECT unnest(string_split_regex(lower(text), '[^\\p{L}\\p{N}\\s]+|\\n')) AS p FROM benchmark)), unnest(range(1, len(w))) AS t(i))"


@query(sql(f"SELECT s AS support, count(*) AS found, count(t.phrase) AS right, round(count(t.phrase) / count(*), 6) AS precision, round(count(t.phrase) / (SELECT count(*) FROM {_TRUTH}), 6) AS recall FROM (SELECT * FROM cnt WHERE n > 1) c LEFT JOIN {_TRUTH} t ON t.phrase = c.phrase JOIN (SELECT unnest([10, 15, 20, 40, 80])::BIGINT AS s) ON c.cnt >= s GROUP BY s", "cnt"))
def support_curve(spark, d):
    truth = text.chunk(scan(spark, d, "benchmark"), id_col="item_id").select(F.explode(mining.ngrams_of(F.col("toks"), 2)).alias("phrase"))
    out = evaluate.support_curve(_stages(spark, d).mined.counts, truth, [10, 15, 20, 40, 80])
    return out.withColumn("precision", _r(F.col("precision"))).withColumn("recall", _r(F.col("recall")))


_DOM = "(SELECT doc_id, arg_max(k, struct_pack(c := c, k := -k)) AS k FROM dk GROUP BY doc_id)"


@query(sql(f"SELECT lang, k, count(*) AS docs FROM {_DOM} m JOIN documents USING (doc_id) GROUP BY lang, k", "dk", fitted=True))
def topic_lang_agreement(spark, d):
    s = _stages(spark, d)
    return evaluate.topic_agreement(s.fitted, s.docs)


@query(sql(f"""WITH c AS (SELECT k, lang, count(*) AS c FROM {_DOM} m JOIN documents USING (doc_id) GROUP BY ALL), f AS (SELECT c, sum(c) OVER (PARTITION BY k) AS nk, sum(c) OVER (PARTITION BY lang) AS nt, max(c) OVER (PARTITION BY k) AS best, sum(c) OVER () AS n FROM c)
SELECT round(sum(best * c / nk / n), 6) AS purity, round(2 * sum(c / n * ln(c * n / (nk * nt))) / (sum(-c / n * ln(nk / n)) + sum(-c / n * ln(nt / n))), 6) AS nmi FROM f""".replace("WITH c AS", "SELECT * FROM (WITH c AS", 1) + ")", "dk", fitted=True))
def purity_nmi(spark, d):
    s = _stages(spark, d)
    out = evaluate.agreement(evaluate.dominant_topic(s.fitted), s.docs.select("doc_id", "lang"), "lang")
    return out.select(_r(F.col("purity")).alias("purity"), _r(F.col("nmi")).alias("nmi"))


# --- baselines -----------------------------------------------------------------------------------------------------------


@query(sql("SELECT v, w, k, count(*) AS n FROM (SELECT word AS v, z AS k, lead(word) OVER o AS w, lead(z) OVER o AS z2 FROM lw WINDOW o AS (PARTITION BY doc_id, chunk_no ORDER BY pos)) WHERE w IS NOT NULL AND k = z2 GROUP BY ALL", "lw", fitted=True))
def posthoc_pairs(spark, d):
    return packed.adjacent_pairs(_stages(spark, d).fitted_docs)


_SETS = """(SELECT DISTINCT doc_id, z AS k, word FROM lw) """


@query(sql(f"""SELECT a.k, a.word || ' ' || b.word AS items, count(*) AS f FROM (SELECT x.* FROM {_SETS} x JOIN (SELECT k, word FROM {_SETS} GROUP BY ALL HAVING count(*) >= 40) o ON o.k = x.k AND o.word = x.word) a
    JOIN (SELECT x.* FROM {_SETS} x JOIN (SELECT k, word FROM {_SETS} GROUP BY ALL HAVING count(*) >= 40) o ON o.k = x.k AND o.word = x.word) b ON a.doc_id = b.doc_id AND a.k = b.k AND a.word < b.word GROUP BY ALL HAVING count(*) >= 40""", "lw", fitted=True))
def itemset_pairs(spark, d):
    """Frequent word pairs of one topic in one document, without the completeness filter."""
    rows = baselines.itemset_keyphrases(_stages(spark, d).fitted_words, min_support=40, max_size=2, complete=0.0)
    return rows.where(F.size("items") == 2).select("k", F.concat_ws(" ", "items").alias("items"), "f")


@query(sql("""SELECT phrase, cnt, docs, importance FROM (SELECT c.phrase, c.cnt, g.docs, round(c.cnt * ln((SELECT count(DISTINCT doc_id) FROM ch)::DOUBLE / g.docs), 6) AS importance FROM cnt c JOIN (SELECT phrase, count(DISTINCT doc_id) AS docs FROM grams WHERE n > 1 GROUP BY phrase) g ON g.phrase = c.phrase WHERE c.n > 1) ORDER BY importance DESC, phrase LIMIT 100""", "ch", "cnt", "grams"))
def rank_and_cut(spark, d):
    """The hundred best candidates: the cut is the method."""
    s = _stages(spark, d)
    return baselines.rank_and_cut(s.mined.counts, s.chunks, 100)


_EN = ", ".join(repr(w) for w in text.STOP_WORDS["en"])


@query(sql(f"SELECT n, phrase, count(*) AS cnt FROM (SELECT n::INT AS n, array_to_string(toks[i:i + n - 1], ' ') AS phrase FROM raw, unnest(range(1, 4)) AS a(n), unnest(range(1, len(toks) - n + 2)) AS b(i)) WHERE n > 1 AND NOT regexp_matches(phrase, '[0-9]') AND string_split(phrase, ' ')[1] NOT IN ({_EN}) AND string_split(phrase, ' ')[-1] NOT IN ({_EN}) GROUP BY ALL HAVING count(*) >= 10", "raw"))
def rule_filter(spark, d):
    counts = mining.frequent_phrases(_stages(spark, d).raw.select("doc_id", "toks"), SUPPORT, 3).counts
    return baselines.rule_filter(counts, text.STOP_WORDS["en"])


@query("""WITH b AS (SELECT DISTINCT l_orderkey AS o, unnest(string_split(p_name, ' ')) AS w FROM lineitem JOIN part ON l_partkey = p_partkey), n AS (SELECT count(DISTINCT o) AS n FROM b)
SELECT items, f AS freq FROM (SELECT w AS items, count(*) AS f FROM b GROUP BY w UNION ALL SELECT x.w || ' ' || y.w, count(*) FROM b x JOIN b y ON x.o = y.o AND x.w < y.w GROUP BY ALL), n WHERE f >= ceil(0.02 * n)""")
def basket_itemsets(spark, d):
    sets = baselines.itemsets(workloads.baskets(spark, d).select("items"), 0.02)
    return sets.select(F.concat_ws(" ", F.array_sort("items")).alias("items"), "freq")


# --- fitted models, rows only --------------------------------------------------------------------------------------------


@query()
def cctm_gibbs(spark, d):
    s = _whole(spark, d)
    return rank.topic_view(s.fit(optimise_every=5).state, surfaces=s.surfaces)


@query()
def lda_gibbs(spark, d):
    return rank.topic_view(baselines.lda(_stages(spark, d).chunks, n_topics=K, sweeps=20, doc_prior=DOC_PRIOR).state)


@query()
def fold_in(spark, d):
    """Topic shares of the held-out eighth of the documents under word distributions of the rest."""
    s = _whole(spark, d)
    out = evaluate.held_out(F.col("doc_id"))
    model = topics.fit(s.cliques.where(~out), K, sweeps=10, doc_prior=DOC_PRIOR)
    return topics.infer(s.cliques.where(out), topics.phi(model.state, K), K)


@query()
def topics_auto(spark, d):
    return rank.top(rank.word_frequency(topics.fit(_whole(spark, d).cliques, "auto", sweeps=20, k_max=8).state), 5, F.col("tf"), "word")


@query()
def posthoc_merge(spark, d):
    """Phrases that the fitted word model's words are merged to, until no pair is significant."""
    rows = packed.rows(baselines.posthoc_docs(_stages(spark, d).sampled_docs, n_perm=20))
    return rows.where(F.contains("word", F.lit(" "))).groupBy("word", "z").agg(F.count("*").alias("n"))


@query()
def bigram_switch(spark, d):
    return baselines.bigram_switch(_stages(spark, d).chunks, n_topics=K, sweeps=10).where("len > 1").groupBy("phrase", "z").agg(F.count("*").alias("n"))


@query()
def pitman_yor(spark, d):
    """The sequential baseline: one task goes through all documents."""
    return baselines.pitman_yor_phrases(_stages(spark, d).chunks, n_topics=K, sweeps=2).where("len > 1").groupBy("phrase", "z").agg(F.count("*").alias("n"))


@query()
def lda_variational(spark, d):
    return baselines.lda_variational(_stages(spark, d).chunks, K, 5)


@query()
def pipeline_flagship(spark, d):
    view, _, _ = pipeline.run(scan(spark, d, "documents", "doc_id", "text", "lang"), pipeline.Config(stem=True, optimise_every=5))
    return view


# --- operators around the methods ----------------------------------------------------------------------------------------


@query("SELECT lang, source, count(*) AS docs, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY ALL")
def scan_pruned_columns(spark, d):
    return scan(spark, d, "documents", "lang", "source", "n_chars").groupBy("lang", "source").agg(F.count("*").alias("docs"), F.sum("n_chars").alias("chars"))


@query("SELECT doc_id, lang, source, n_chars, md5(text) AS text_md5 FROM documents")
def scan_documents(spark, d):
    return scan(spark, d, "documents").select("doc_id", "lang", "source", "n_chars", F.md5("text").alias("text_md5"))


@query("SELECT doc_id, lang, n_chars FROM documents WHERE lang IN ('en', 'de') AND n_chars BETWEEN 500 AND 2500 AND source IS NOT NULL")
def filter_lang_len(spark, d):
    return scan(spark, d, "documents", "doc_id", "lang", "n_chars", "source").where(F.col("lang").isin("en", "de") & F.col("n_chars").between(500, 2500) & F.col("source").isNotNull()).drop("source")


@query("SELECT page_id, replace(replace(replace(replace(replace(replace(regexp_extract(html, '(?s)<title>(.*?)</title>', 1), '&lt;', '<'), '&gt;', '>'), '&quot;', '\"'), '&#39;', ''''), '&nbsp;', ' '), '&amp;', '&') AS title FROM pages")
def page_titles(spark, d):
    return scan(spark, d, "pages", "page_id", "html").select("page_id", text.page_title(F.col("html")).alias("title"))


@query(r"""SELECT page_id, md5(replace(replace(replace(replace(replace(replace(regexp_replace(array_to_string(regexp_extract_all(regexp_replace(html, '(?s)<(script|style|nav)\b.*?</(script|style|nav)>|<!--.*?-->', ' ', 'g'), '(?s)<p>(.*?)</p>', 1), chr(10)), '<[^>]*>', '', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&nbsp;', ' '), '&amp;', '&')) AS body_md5 FROM pages""")
def page_bodies(spark, d):
    return scan(spark, d, "pages", "page_id", "html").select("page_id", F.md5(text.page_body(F.col("html"))).alias("body_md5"))


@query(sql("SELECT c.doc_id, count(*) AS live FROM (SELECT doc_id, unnest(list_transform(range(1, len(toks)), lambda i: toks[i] || ' ' || toks[i + 1])) AS phrase FROM ch) c SEMI JOIN (SELECT phrase FROM cnt WHERE n = 2) f ON f.phrase = c.phrase GROUP BY c.doc_id", "ch", "cnt"))
def join_semi_positions(spark, d):
    s = _stages(spark, d)
    starts = s.chunks.select("doc_id", F.explode(mining.ngrams_of(F.col("toks"), 2)).alias("phrase"))
    return starts.join(s.mined.counts.where("n = 2"), "phrase", "left_semi").groupBy("doc_id").agg(F.count("*").alias("live"))


@query(sql(f"SELECT word, count(*) AS cnt FROM (SELECT unnest(toks) AS word FROM raw) WHERE word NOT IN ({_EN}) GROUP BY word", "raw"))
def join_anti_stopwords(spark, d):
    stop = spark.createDataFrame([(w,) for w in text.STOP_WORDS["en"]], "stop string")  # a fixed list
    words = _stages(spark, d).raw.select(F.explode("toks").alias("word"))
    return words.join(F.broadcast(stop), F.col("word") == F.col("stop"), "left_anti").groupBy("word").agg(F.count("*").alias("cnt"))


@query("SELECT d.doc_id, d.lang, l.quality, l.toxic FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id")
def join_left_outer_labels(spark, d):
    return scan(spark, d, "documents", "doc_id", "lang").join(scan(spark, d, "labels"), "doc_id", "left").select("doc_id", "lang", "quality", "toxic")


@query(sql("SELECT p.doc_id, p.chunk_no, p.g, t.pos AS at_pos FROM part p JOIN (SELECT doc_id, chunk_no, (i - 1)::INT AS pos FROM ch, unnest(range(1, len(toks) + 1)) AS t(i) WHERE len(toks[i]) >= 12) t ON t.doc_id = p.doc_id AND t.chunk_no = p.chunk_no AND t.pos >= p.start AND t.pos < p.start + p.n_words", "part", "ch"))
def join_range_spans(spark, d):
    """The phrase instance over each long word."""
    s = _stages(spark, d)
    key = F.concat_ws("|", "doc_id", "chunk_no")
    points = s.chunks.select(key.alias("chunk_key"), F.posexplode("toks").alias("at_pos", "word")).where(F.length("word") >= 12).drop("word")
    spans = s.parts.select(key.alias("chunk_key"), "doc_id", "chunk_no", "g", F.col("start").alias("s"), (F.col("start") + F.col("len")).alias("e"))
    return relational.range_join(points, spans, "chunk_key", "at_pos", "s", "e", 16).select("doc_id", "chunk_no", "g", "at_pos")


@query(sql("SELECT DISTINCT a.phrase AS inner_p, b.phrase AS outer_p FROM cnt a JOIN cnt b ON a.n < b.n AND contains(' ' || b.phrase || ' ', ' ' || a.phrase || ' ') WHERE b.n > 1", "cnt"))
def join_theta_containment(spark, d):
    return relational.containment(_stages(spark, d).mined.counts)


@query("SELECT c.event_id, p.event_type AS last_type, p.value AS last_value FROM (SELECT * FROM events WHERE event_type = 'purchase') c ASOF LEFT JOIN (SELECT user_id, ts, arg_max(event_type, event_id) AS event_type, arg_max(value, event_id) AS value FROM events WHERE event_type <> 'purchase' GROUP BY user_id, ts) p ON c.user_id = p.user_id AND c.ts >= p.ts")
def join_asof_events(spark, d):
    """Each purchase with the user's last other event."""
    ev = scan(spark, d, "events", "event_id", "ts", "user_id", "event_type", "value")
    other = ev.where("event_type <> 'purchase'").groupBy("user_id", "ts").agg(F.max_by("event_type", "event_id").alias("last_type"), F.max_by("value", "event_id").alias("last_value"))
    return relational.asof_join(ev.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), other, "user_id", "ts", "ts", ["last_type", "last_value"]).select("event_id", "last_type", "last_value")


@query("SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def join_interval_events(spark, d):
    ev = scan(spark, d, "events", "event_id", "ts", "user_id", "event_type")
    a = ev.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("ts").alias("t0"))
    b = ev.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("u"), F.col("ts").alias("t1"))
    return a.join(b, (F.col("user_id") == F.col("u")) & (F.col("t1") > F.col("t0")) & (F.col("t1") <= F.col("t0") + F.expr("INTERVAL 1 HOUR"))).select("click_id", "purchase_id")


def _grouped(kind: str) -> str:
    return sql(f"SELECT lang, source, n, count(*) AS grams FROM grams WHERE n <= 3 GROUP BY {kind}", "grams")


def _gram_rows(spark, d):
    c = _stages(spark, d).chunks
    return c.select("lang", "source", F.explode(F.flatten(F.array(*[F.transform(mining.ngrams_of(F.col("toks"), n), _tagged(n)) for n in (1, 2, 3)]))).alias("n"))


def _tagged(n):
    return lambda g: F.lit(n)


@query(_grouped("ROLLUP (lang, source, n)"))
def ngram_rollup_lang_source(spark, d):
    return _gram_rows(spark, d).rollup("lang", "source", "n").agg(F.count("*").alias("grams"))


@query(_grouped("CUBE (lang, source, n)"))
def ngram_cube(spark, d):
    return _gram_rows(spark, d).cube("lang", "source", "n").agg(F.count("*").alias("grams"))


@query(_grouped("GROUPING SETS ((lang, n), (source), ())"))
def ngram_grouping_sets(spark, d):
    rows = _gram_rows(spark, d)
    return rows.groupingSets([[rows.lang, rows.n], [rows.source], []], "lang", "source", "n").agg(F.count("*").alias("grams"))


@query(sql("SELECT count(DISTINCT word) AS words FROM (SELECT unnest(toks) AS word FROM ch)", "ch"))
def distinct_words(spark, d):
    return _stages(spark, d).chunks.select(F.explode("toks").alias("word")).agg(F.count_distinct("word").alias("words"))


@query(sql("SELECT phrase, coalesce(sum(tf) FILTER (WHERE k = 0), 0)::BIGINT AS t0, coalesce(sum(tf) FILTER (WHERE k = 1), 0)::BIGINT AS t1, coalesce(sum(tf) FILTER (WHERE k = 2), 0)::BIGINT AS t2, coalesce(sum(tf) FILTER (WHERE k = 3), 0)::BIGINT AS t3 FROM tf WHERE n_words > 1 GROUP BY phrase", "tf", fitted=True))
def topic_pivot(spark, d):
    p = rank.topical_frequency(_stages(spark, d).fitted).where("n_words > 1").groupBy("phrase").pivot("k", list(range(K))).agg(F.sum("tf"))
    return p.select("phrase", *[F.coalesce(F.col(str(k)), F.lit(0)).alias(f"t{k}") for k in range(K)])


@query(sql("SELECT toks[i] || ' ' || toks[i + 1] AS bigram, count(*) AS n FROM ch, unnest(range(1, len(toks))) AS t(i) GROUP BY ALL", "ch"))
def bigrams_by_lead(spark, d):
    w = Window.partitionBy("doc_id", "chunk_no").orderBy("pos")
    rows = _stages(spark, d).chunks.select("doc_id", "chunk_no", F.posexplode("toks").alias("pos", "word")).withColumn("next", F.lead("word").over(w)).where("next is not null")
    return rows.groupBy(F.concat_ws(" ", "word", "next").alias("bigram")).agg(F.count("*").alias("n"))


@query(sql("SELECT lang, phrase, n, rank::INT AS rank FROM (SELECT lang, phrase, count(*) AS n, row_number() OVER (PARTITION BY lang ORDER BY count(*) DESC, phrase) AS rank FROM grams WHERE n = 2 GROUP BY lang, phrase) WHERE rank <= 10", "grams"))
def topk_phrases_per_lang(spark, d):
    g = _stages(spark, d).chunks.select("lang", F.explode(mining.ngrams_of(F.col("toks"), 2)).alias("phrase")).groupBy("lang", "phrase").agg(F.count("*").alias("n"))
    return rank.top(g, 10, F.col("n"), "phrase", group="lang").select("lang", "phrase", "n", "rank")


@query(sql("SELECT phrase, n_words, cnt FROM bagged WHERE n_words > 1 ORDER BY cnt DESC, phrase LIMIT 50", "bagged"))
def top_phrases_global(spark, d):
    return segment.bag(_stages(spark, d).parts).where("n_words > 1").orderBy(F.desc("cnt"), "phrase").limit(50)


@query(sql("SELECT k, phrase, round(sum(tf) OVER (PARTITION BY k ORDER BY tf DESC, phrase ROWS UNBOUNDED PRECEDING) / sum(tf) OVER (PARTITION BY k), 9) AS cdf FROM tf WHERE n_words > 1", "tf", fitted=True))
def cdf_running_sum(spark, d):
    tf = rank.topical_frequency(_stages(spark, d).fitted).where("n_words > 1")
    return relational.cumulative(tf, ["k"], [F.desc("tf"), F.col("phrase")], "tf").select("k", "phrase", _r(F.col("cdf"), 9).alias("cdf"))


@query(sql("SELECT doc_id, run, string_agg(word, ' ' ORDER BY i) AS phrase, count(*)::INT AS len, last(z ORDER BY i) AS z FROM (SELECT *, sum(1 - x) OVER (PARTITION BY doc_id ORDER BY i ROWS UNBOUNDED PRECEDING) AS run FROM (SELECT doc_id, row_number() OVER (PARTITION BY doc_id ORDER BY chunk_no, pos) AS i, word, z, CASE WHEN pos > 0 AND z = lag(z) OVER (PARTITION BY doc_id ORDER BY chunk_no, pos) THEN 1 ELSE 0 END AS x FROM lw)) GROUP BY doc_id, run", "lw", fitted=True))
def glued_runs(spark, d):
    """Runs of neighbours with one topic in a chunk, by gaps and islands."""
    return packed.glued_runs(packed.same_topic(_stages(spark, d).fitted_docs))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS mean5, dense_rank() OVER (PARTITION BY user_id ORDER BY event_type)::INT AS type_rank FROM events")
def moving_avg_events(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    return scan(spark, d, "events", "event_id", "ts", "user_id", "event_type", "value").select("event_id", _r(F.avg("value").over(w)).alias("mean5"), F.dense_rank().over(Window.partitionBy("user_id").orderBy("event_type")).alias("type_rank"))


def _lang_grams(spark, d, *langs):
    return [_stages(spark, d).chunks.where(F.col("lang") == c).select(F.explode(mining.ngrams_of(F.col("toks"), 2)).alias("phrase")) for c in langs]


@query(sql("SELECT phrase FROM grams WHERE n = 2 AND lang = 'en' INTERSECT SELECT phrase FROM grams WHERE n = 2 AND lang = 'de'", "grams"))
def phrases_common_langs(spark, d):
    en, de = _lang_grams(spark, d, "en", "de")
    return en.intersect(de)


@query(sql("SELECT phrase FROM grams WHERE n = 2 AND lang = 'en' EXCEPT SELECT phrase FROM grams WHERE n = 2 AND lang <> 'en'", "grams"))
def phrases_only_en(spark, d):
    en, de, fr, es = _lang_grams(spark, d, "en", "de", "fr", "es")
    return en.distinct().subtract(de.unionByName(fr).unionByName(es))


_TOKENS_OF = r"list_filter(string_split_regex(p, '\s+'), lambda x: x <> '')"
_ANY = r"(SELECT unnest(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS phrase FROM (SELECT " + _TOKENS_OF + r" AS w FROM (SELECT unnest(string_split_regex(lower(text), '[^\p{L}\p{N}\s]+|\n')) AS p FROM {t})))"


@query(f"SELECT phrase, count(*) AS n FROM (SELECT * FROM {_ANY.replace('{t}', 'benchmark')} UNION ALL SELECT * FROM {_ANY.replace('{t}', 'conversations')}) GROUP BY phrase")
def phrases_union_tables(spark, d):
    sides = [text.chunk(scan(spark, d, t), id_col=i).select(F.explode(mining.ngrams_of(F.col("toks"), 2)).alias("phrase")) for t, i in (("benchmark", "item_id"), ("conversations", "conv_id"))]
    return sides[0].unionByName(sides[1]).groupBy("phrase").agg(F.count("*").alias("n"))


@query("SELECT doc_id, length(trim(text)) AS len, lower(substr(text, 1, 20)) AS head, levenshtein(substr(md5(text), 1, 20), substr(md5(text), 3, 20)) AS shift, length(text) - length(replace(text, ' ', '')) AS blanks, md5(translate(text, 'ae', 'ea')) AS swapped FROM documents")
def string_profile(spark, d):
    t = F.col("text")
    return scan(spark, d, "documents", "doc_id", "text").select("doc_id", F.length(F.trim(t)).cast("long").alias("len"), F.lower(F.substring(t, 1, 20)).alias("head"), F.levenshtein(F.substring(F.md5(t), 1, 20), F.substring(F.md5(t), 3, 20)).cast("long").alias("shift"), (F.length(t) - F.length(F.replace(t, F.lit(" "), F.lit("")))).cast("long").alias("blanks"), F.md5(F.translate(t, "ae", "ea")).alias("swapped"))


@query(sql("SELECT doc_id, chunk_no, array_to_string(list_sort(list_distinct(toks)), ' ') AS word_set, len(toks)::INT AS n, toks[-1] AS last_word, array_to_string(list_transform(toks[1:3], lambda w: reverse(w)), '+') AS head FROM ch", "ch"))
def array_phrase_algebra(spark, d):
    return _stages(spark, d).chunks.select("doc_id", "chunk_no", F.concat_ws(" ", F.array_sort(F.array_distinct("toks"))).alias("word_set"), F.size("toks").alias("n"), F.element_at("toks", -1).alias("last_word"), F.concat_ws("+", F.transform(F.slice("toks", 1, 3), F.reverse)).alias("head"))


@query(sql("SELECT doc_id, count(*) AS words, max(c) AS most FROM (SELECT doc_id, word, count(*) AS c FROM (SELECT doc_id, unnest(toks) AS word FROM ch) GROUP BY ALL) GROUP BY doc_id", "ch"))
def map_word_counts(spark, d):
    words = _stages(spark, d).chunks.select("doc_id", F.explode("toks").alias("word")).groupBy("doc_id", "word").agg(F.count("*").alias("c"))
    maps = words.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("word", "c"))).alias("m"))
    return maps.select("doc_id", F.size("m").cast("long").alias("words"), F.array_max(F.map_values("m")).alias("most"))


@query("SELECT date_trunc('day', ts)::TIMESTAMP AS day, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def events_daily(spark, d):
    return scan(spark, d, "events", "ts", "event_type", "value").groupBy(F.date_trunc("day", "ts").alias("day"), "event_type").agg(F.count("*").alias("n"), _r(F.sum("value"), 4).alias("total"))


@query("SELECT event_type, sum(CAST(json_extract(props, '$.k') AS BIGINT))::BIGINT AS k_sum, count(json_extract(props, '$.k')) AS with_k FROM events GROUP BY event_type")
def events_props_json(spark, d):
    k = F.from_json("props", "k long")["k"]
    return scan(spark, d, "events", "event_type", "props").groupBy("event_type").agg(F.sum(k).alias("k_sum"), F.count(k).alias("with_k"))


@query("SELECT time_bucket(INTERVAL 1 DAY, ts)::TIMESTAMP AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def events_tumbling(spark, d):
    return scan(spark, d, "events", "ts", "event_type").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


@query("SELECT time_bucket(INTERVAL 6 HOUR, ts)::TIMESTAMP - i * INTERVAL 6 HOUR AS start, event_type, count(*) AS n FROM events, range(4) AS t(i) GROUP BY ALL")
def events_sliding(spark, d):
    return scan(spark, d, "events", "ts", "event_type").groupBy(F.window("ts", "1 day", "6 hours").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


_SESSIONS = """(SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS sid FROM (
    SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL {gap} THEN 1 ELSE 0 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)))"""


@query(f"SELECT user_id, min(ts)::TIMESTAMP AS start, count(*) AS n FROM {_SESSIONS.format(gap='30 MINUTE')} GROUP BY user_id, sid")
def events_sessions(spark, d):
    return scan(spark, d, "events", "ts", "user_id").groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


@query(f"""WITH s AS (SELECT list(event_type ORDER BY ts, event_id) AS toks FROM {_SESSIONS.format(gap='1 DAY')} GROUP BY user_id, sid)
SELECT n::INT AS n, array_to_string(toks[i:i + n - 1], ' ') AS phrase, count(*) AS cnt FROM s, unnest(range(1, 4)) AS a(n), unnest(range(1, len(toks) - n + 2)) AS b(i) GROUP BY ALL HAVING count(*) >= 10""")
def session_phrases(spark, d):
    return mining.frequent_phrases(workloads.action_sequences(spark, d, "1 day"), 10, 3).counts


@query(sql("SELECT lang, phrase, count(*) AS n FROM (SELECT lang, unnest(list_transform(range(1, len(toks)), lambda i: toks[i] || ' ' || toks[i + 1])) AS phrase FROM raw WHERE lang = 'es') GROUP BY ALL", "raw"))
def udtf_ngrams(spark, d):
    """Bigrams by the Python table function, called from SQL."""
    sqlsurface.register(spark)
    _stages(spark, d).raw.where("lang = 'es'").select("lang", "toks").createOrReplaceTempView("pw_chunks")
    return spark.sql("SELECT c.lang, t.phrase, count(*) AS n FROM pw_chunks c, LATERAL ngrams(c.toks, 2) t GROUP BY c.lang, t.phrase")


@query(sql(f"SELECT c.phrase, round((f12 - a.cnt::DOUBLE * b.cnt / l.l) / sqrt(f12), 6) AS sig {_PAIRS}", "cnt", "l"))
def sql_significance(spark, d):
    s = _stages(spark, d)
    sqlsurface.register(spark)
    s.mined.counts.createOrReplaceTempView("pw_counts")
    return spark.sql(f"""SELECT c.phrase, round(phrase_sig(a.cnt, b.cnt, c.cnt, {s.mined.tokens}), 6) AS sig FROM pw_counts c
        JOIN pw_counts a ON a.n = 1 AND a.phrase = split(c.phrase, ' ')[0] JOIN pw_counts b ON b.n = 1 AND b.phrase = split(c.phrase, ' ')[1] WHERE c.n = 2""")


@query(sql("SELECT phrase, k, tf FROM tf WHERE n_words > 1", "tf", fitted=True))
def sql_topical_frequency(spark, d):
    _stages(spark, d).fitted.createOrReplaceTempView("pw_state")
    return spark.sql("SELECT concat_ws(' ', words) AS phrase, z AS k, count(*) AS tf FROM pw_state WHERE size(words) > 1 GROUP BY ALL")


@query("SELECT doc_id, lang FROM documents WHERE ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT / 4294967296.0 < 0.25")
def hash_sample_docs(spark, d):
    """A sampling operator: a quarter of the documents, the same everywhere."""
    return workloads.sampled(scan(spark, d, "documents", "doc_id", "lang"), 0.25)


@query("SELECT doc_id, lang FROM documents WHERE ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT / 4294967296.0 < CASE lang WHEN 'en' THEN 0.1 WHEN 'de' THEN 0.5 WHEN 'fr' THEN 0.5 ELSE 0.0 END")
def stratified_sample_docs(spark, d):
    """A sampling operator: a share of its own for each language."""
    return workloads.stratified(scan(spark, d, "documents", "doc_id", "lang"), "lang", {"en": 0.1, "de": 0.5, "fr": 0.5})


_RAW_OF = r"(SELECT " + _TOKENS_OF + r" AS toks FROM (SELECT unnest(string_split_regex(lower(text), '[^\p{L}\p{N}\s]+|\n')) AS p FROM {src}))"


@query(f"SELECT n::INT AS n, array_to_string(toks[i:i + n - 1], ' ') AS phrase, count(*) AS cnt FROM {_RAW_OF.replace('{src}', '(SELECT text FROM conversations WHERE role = ' + chr(39) + 'user' + chr(39) + ')')}, unnest(range(1, 4)) AS a(n), unnest(range(1, len(toks) - n + 2)) AS b(i) GROUP BY ALL HAVING count(*) >= 5")
def review_phrases(spark, d):
    return mining.frequent_phrases(text.chunk(workloads.reviews(spark, d)).select("doc_id", "toks"), 5, 3).counts


_ENTITIES = (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&nbsp;", " "), ("&amp;", "&"))


def _unescaped(column: str) -> str:
    for entity, char in _ENTITIES:
        column = f"replace({column}, '{entity}', '{char}')"
    return column


_PAGE_LANG = r"""regexp_extract(html, '<html lang="(\w+)"', 1)"""
_TITLES = rf"""SELECT 'd' || doc_id AS key, list_filter(string_split_regex(lower(text), '[^\p{{L}}\p{{N}}\s]+|\n'), lambda p: trim(p) <> '')[1] AS text, lang FROM corpus
    UNION ALL SELECT 'p' || page_id, {_unescaped("regexp_extract(html, '(?s)<title>(.*?)</title>', 1)")}, {_PAGE_LANG} FROM pages UNION ALL SELECT 'n' || p_partkey, p_name, 'en' FROM part_names"""
_BODY = r"regexp_replace(array_to_string(regexp_extract_all(regexp_replace(html, '(?s)<(script|style|nav)\b.*?</(script|style|nav)>|<!--.*?-->', ' ', 'g'), '(?s)<p>(.*?)</p>', 1), chr(10)), '<[^>]*>', '', 'g')"
_BODIES = f"SELECT text, lang FROM corpus WHERE n_chars > 2500 UNION ALL SELECT {_unescaped(_BODY)}, {_PAGE_LANG} FROM pages"
_SHARE = "('0x' || substr(md5({key}::VARCHAR), 1, 8))::BIGINT / 4294967296.0 < {part}"


def _mined_sql(corpus: str, support: int) -> str:
    """Counts of a corpus that a relation gives; it reads the tables by other names, as the shared expressions use theirs."""
    whole = sql(f"SELECT n, phrase, count(*) AS cnt FROM grams GROUP BY n, phrase HAVING count(*) >= {support}", "grams").replace("FROM documents", "FROM corpus_rows")
    rows = f"SELECT row_number() OVER () AS doc_id, text, lang, NULL::VARCHAR AS source FROM ({corpus}) x"
    return whole.replace("WITH RECURSIVE ", f"WITH RECURSIVE corpus AS (SELECT * FROM documents), part_names AS (SELECT p_partkey, p_name FROM part), corpus_rows AS MATERIALIZED ({rows}),\n", 1)


def _mined(docs, support: int):
    return mining.frequent_phrases(text.drop_stopwords(text.chunk(docs, keep=("lang",))), support, LONGEST).counts


@query(_mined_sql(_TITLES, 5))
def title_phrases(spark, d):
    return _mined(workloads.titles(spark, d), 5)


@query(_mined_sql(f"SELECT text, lang FROM ({_TITLES}) t WHERE {_SHARE.format(key='key', part='1.0 / 38')}", 2))
def title_phrases_sampled(spark, d):
    """The workload is a sample."""
    return _mined(workloads.titles(spark, d, 1 / 38), 2)


@query(_mined_sql("SELECT string_split(text, chr(10))[1] AS text, lang FROM corpus", 5))
def venue_title_phrases(spark, d):
    return _mined(workloads.by_source(spark, d), 5)


@query(_mined_sql("SELECT text, lang FROM corpus WHERE n_chars <= 2500 AND lang = 'en'", 5))
def abstract_phrases(spark, d):
    return _mined(workloads.abstracts(spark, d), 5)


@query(_mined_sql(f"SELECT text, lang FROM corpus WHERE n_chars <= 2500 AND lang = 'en' AND {_SHARE.format(key='doc_id', part='20.0 / 529')}", 2))
def abstract_phrases_sampled(spark, d):
    """The workload is a sample."""
    return _mined(workloads.sampled(workloads.abstracts(spark, d), 20 / 529), 2)


@query(_mined_sql(_BODIES, 10))
def article_phrases(spark, d):
    return _mined(workloads.articles(spark, d), 10)


# --- compared methods on fitted models -----------------------------------------------------------------------------------


@query()
def phrase_lists_by_method(spark, d):
    """Ten phrases a topic of each of the five methods, all fitted on all documents."""
    return methods.lists_of(_stages(spark, d))


@query()
def intrusion_by_method(spark, d):
    """Twenty questions a method, three simulated raters (documents, chunks and sources as units)."""
    s = _stages(spark, d)
    view = methods.lists_of(s)
    words = s.chunks.select("doc_id", "chunk_no", "source", F.explode("toks").alias("item"))
    units = {"document": F.col("doc_id").cast("string"), "chunk": F.concat_ws("|", "doc_id", "chunk_no"), "source": F.col("source")}
    held = {rater: settle(evaluate.holders(words.select(unit.alias("unit"), "item"), view), "holders") for rater, unit in units.items()}
    out = None
    for method in methods.METHODS:
        q = settle(evaluate.intrusion_questions(view.where(F.col("method") == method).drop("method")), "questions")
        for rater, u in held.items():
            one = evaluate.intrusion_score(q, evaluate.simulated_answers(q, u, rater)).select(F.lit(method).alias("method"), "rater", "answered", "correct")
            out = one if out is None else out.unionByName(one)
    return out


@query()
def coherence_by_method(spark, d):
    """Mean standardised coherence of each method's lists, five raters."""
    s = _stages(spark, d)
    view = methods.lists_of(s)
    held = evaluate.holders(s.chunks.select(F.col("doc_id").alias("unit"), F.explode("toks").alias("item")), view)
    return evaluate.zscore(evaluate.proxy_ratings(view, held.select(F.col("unit").alias("doc_id"), "item"), item_kind="phrase"))


@query()
def quality_by_method(spark, d):
    """Mean standardised phrase quality of each method's lists, five raters."""
    s = _stages(spark, d)
    return evaluate.zscore(evaluate.proxy_qualities(methods.lists_of(s), s.chunks))


@query()
def perplexity_by_sweep(spark, d):
    """Training and held-out perplexity of both models after every second sweep, on abstracts and reviews. A sixteenth of the chunks is
    held out, the same for both models, and scored with its document's topics."""
    out = []
    for corpus, docs, support, threshold in (("abstracts", workloads.abstracts, 5, 3.0), ("reviews", workloads.reviews, 3, 1.0)):
        s = pipeline.stages_of(spark, d, None, docs, n_topics=10, min_support=support, sig_threshold=threshold)
        hidden = evaluate.held_phrase(F.col("doc_id"), F.col("chunk_no"))
        held = s.chunks.where(hidden).select("doc_id", F.col("toks").alias("words"))
        cliques = s.parts.where(~hidden).select("doc_id", "g", F.split("phrase", " ").alias("words"))
        for model, units in (("cliques", cliques), ("words", topics.singletons(s.chunks.where(~hidden)))):
            trace = topics.fit(units, 10, sweeps=10, doc_prior=0.5, trace_every=2, held=held).trace
            out += [(corpus, model, t["sweep"], t["tokens"], t["perplexity"], t["held_tokens"], t["held_perplexity"]) for t in trace]
    return spark.createDataFrame(out, "corpus string, model string, sweep int, tokens long, perplexity double, held_tokens long, held_perplexity double")
