"""Chunks, stop words, vocabularies, surface forms and web text, all in built-in column functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: A phrase never runs over these: anything but letters, digits and blanks, and line ends.
BOUNDARY = r"[^\p{L}\p{N}\s]+|\n"

#: Stop words (fixed values).
STOP_WORDS = {
    "en": "a an and are as at be been but by for from had has have he her his in is it its not of on or she that the their they this to was were which will with".split(),
    "fr": "au aux avec ce ces dans de des du elle en est et il ils la le les leur mais ne nous on ou par pas pour qu que qui sa se ses son sur un une vous".split(),
    "de": "als am an auch auf aus bei das dem den der des die durch ein eine einen einer es für im in ist mit nach nicht sich sie sind über um und von vor war werden wie zu zum zur".split(),
    "es": "a al como con de del el en es esta este ha la las le lo los más no o para pero por que se sin sobre su sus un una y".split(),
}


def tokens_of(part: Column) -> Column:
    return F.filter(F.split(part, r"\s+"), lambda w: w != "")


def chunk(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = (), split: bool = True, boundary: str = BOUNDARY) -> DataFrame:
    """doc_id, chunk_no, toks[, keep]: lower-cased tokens of every part between boundaries. Parts without a token are left out
    but keep their number. split=False takes the whole text, boundaries read as blanks, as one chunk. Null text has no chunk."""
    text = F.lower(F.col(text_col))
    parts = F.split(text, boundary, -1) if split else F.array(F.regexp_replace(text, boundary, " "))
    # tokens come out of the generator, so that lambdas further up read a column and don't split the text again for each element
    rows = docs.select(F.col(id_col).alias("doc_id"), *keep, F.posexplode(F.transform(parts, tokens_of)).alias("chunk_no", "toks"))
    return rows.where(F.size("toks") > 0)


def drop_stopwords(chunks: DataFrame, lang_col: str = "lang", lists: dict[str, list[str]] = STOP_WORDS) -> DataFrame:
    """chunks without stop words of their language; at(array<int>) keeps each token's place in the chunk before."""
    outside = lambda words: lambda t: ~t["word"].isin(*words)
    tagged = F.transform("toks", lambda w, i: F.struct(w.alias("word"), i.cast("int").alias("i")))
    kept = tagged
    for code, words in lists.items():  # a literal list a branch, so no lookup table is built for each row
        kept = F.when(F.col(lang_col) == code, F.filter(tagged, outside(words))).otherwise(kept)
    # a generator again, so that the filter runs once
    others = [c for c in chunks.columns if c != "toks"]
    rows = chunks.select(*others, F.explode(F.array(kept)).alias("kept")).where(F.size("kept") > 0)
    return rows.select(*others, F.transform("kept", lambda t: t["word"]).alias("toks"), F.transform("kept", lambda t: t["i"]).alias("at"))


def apply_stems(chunks: DataFrame, stems: DataFrame) -> DataFrame:
    """chunks with each token's stem in its place: stems (word, stem) holds the words that change. Chunks without such a word are
    not regrouped; ``at`` still says where each token stood, so surfaces show the written form."""
    others = [c for c in chunks.columns if c not in ("doc_id", "chunk_no", "toks")]
    changed = stems.where("word <> stem").select(F.col("word").alias("_word"), "stem")
    rows = chunks.select("doc_id", "chunk_no", F.posexplode("toks").alias("i", "word")).join(changed, F.col("word") == F.col("_word"), "left")
    new = rows.groupBy("doc_id", "chunk_no").agg(F.max(F.col("stem").isNotNull()).alias("hit"), F.transform(F.array_sort(F.collect_list(F.struct("i", F.coalesce("stem", "word").alias("w")))), lambda x: x["w"]).alias("_toks")).where("hit")
    joined = chunks.join(new.select("doc_id", "chunk_no", "_toks"), ["doc_id", "chunk_no"], "left")
    return joined.select("doc_id", "chunk_no", *others, F.coalesce("_toks", "toks").alias("toks"))


def unique_chunks(chunks: DataFrame) -> DataFrame:
    """toks, mult: each distinct chunk once, with its number of copies."""
    return chunks.groupBy("toks").agg(F.count("*").alias("mult"))


def collapse_runs(chunks: DataFrame, longest: int) -> DataFrame:
    """chunks with runs of one token cut to ``longest`` copies; an option against degenerate text, off by default."""
    long_run = lambda x, i: ~F.forall(F.sequence(F.lit(1), F.lit(longest)), lambda j: (i - j >= 0) & (F.get("toks", i - j) == x))
    return chunks.withColumn("toks", F.filter("toks", long_run))


def dense_ids(rows: DataFrame, *order: Column, name: str = "id") -> DataFrame:
    """rows with 0, 1, 2, ... in the given order, without a single-task window: sort by ranges, then add each range's start."""
    from ..sources.io import settle

    ranged = settle(rows.orderBy(*order).withColumn("_at", F.monotonically_increasing_id()), "dense-ids")
    # a row for each partition of the sort
    sizes = ranged.groupBy(F.shiftright("_at", 33).alias("_part")).agg(F.count("*").alias("_n"))
    starts = sizes.select("_part", (F.sum("_n").over(Window.orderBy("_part")) - F.col("_n")).alias("_start"))
    return ranged.withColumn("_part", F.shiftright("_at", 33)).join(starts, "_part").withColumn(name, F.col("_start") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))).drop("_at", "_part", "_start")


def vocabulary(chunks: DataFrame) -> DataFrame:
    """word_id, word, cnt; ids count up from the most frequent word, ties by word."""
    counts = chunks.select(F.explode("toks").alias("word")).groupBy("word").agg(F.count("*").alias("cnt"))
    return dense_ids(counts, F.desc("cnt"), F.col("word"), name="word_id").select("word_id", "word", "cnt")


def encode(chunks: DataFrame, vocab: DataFrame) -> DataFrame:
    """doc_id, chunk_no, ids: chunks with word ids in place of words. The join's way follows the vocabulary's size."""
    long = chunks.select("doc_id", "chunk_no", F.posexplode("toks").alias("pos", "word")).join(vocab.select("word", "word_id"), "word")
    return long.groupBy("doc_id", "chunk_no").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "word_id"))), lambda x: x["word_id"]).alias("ids"))


def surface(raw: DataFrame, spans: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """The text a phrase stood for, stop words between its words included: spans (doc_id, chunk_no, first_at, last_at, phrase)
    over raw chunks (doc_id, chunk_no, toks) -> phrase, surface (most frequent, ties by text), cnt of the phrase. ``known`` (phrase,
    surface) are instances whose text needs no look at the raw chunks."""
    shown = spans.join(raw.select("doc_id", "chunk_no", F.col("toks").alias("raw_toks")), ["doc_id", "chunk_no"]).select("phrase", F.concat_ws(" ", F.slice("raw_toks", F.col("first_at") + 1, F.col("last_at") - F.col("first_at") + 1)).alias("surface"))
    counts = (shown if known is None else shown.unionByName(known)).groupBy("phrase", "surface").agg(F.count("*").alias("n"))
    return counts.groupBy("phrase").agg(F.min_by("surface", F.struct(-F.col("n"), "surface")).alias("surface"), F.sum("n").alias("cnt"))


def word_surfaces(raw: DataFrame, chunks: DataFrame) -> DataFrame:
    """word, surface, cnt: the written form that a token of chunks most often stood for (ties by text); chunks has ``at``."""
    shown = chunks.select("doc_id", "chunk_no", F.explode(F.arrays_zip("toks", "at")).alias("t")).join(raw.select("doc_id", "chunk_no", F.col("toks").alias("raw_toks")), ["doc_id", "chunk_no"])
    counts = shown.select(F.col("t.toks").alias("word"), F.get("raw_toks", F.col("t.at")).alias("surface")).groupBy("word", "surface").agg(F.count("*").alias("n"))
    return counts.groupBy("word").agg(F.min_by("surface", F.struct(-F.col("n"), "surface")).alias("surface"), F.sum("n").alias("cnt"))


def unescape(text: Column) -> Column:
    for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")):
        text = F.replace(text, F.lit(entity), F.lit(char))
    return text


def page_title(html: Column) -> Column:
    return unescape(F.regexp_extract(html, r"(?s)<title>(.*?)</title>", 1))


def page_body(html: Column) -> Column:
    """Paragraph texts, one a line, without scripts, styles, comments, navigation and tags."""
    clean = F.regexp_replace(html, r"(?s)<(script|style|nav)\b.*?</(script|style|nav)>|<!--.*?-->", " ")
    return unescape(F.regexp_replace(F.array_join(F.regexp_extract_all(clean, F.lit(r"(?s)<p>(.*?)</p>"), 1), "\n"), r"<[^>]*>", ""))
