"""Functions for use from SQL: phrase_sig, phrase_key, and the table functions ngrams, phrase_words and phrases."""

from __future__ import annotations

import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from .text import BOUNDARY, STOP_WORDS

# blanks as the engine has them, which are those of ASCII
_BLANKS = r" \t\n\x0b\f\r"
_BOUNDARY, _GAP = regex.compile(BOUNDARY.replace(r"\s", _BLANKS)), regex.compile(f"[{_BLANKS}]+")
#: Phrases that may travel with a table function.
SHIPPED = 2_000_000


def phrases_function(counts: DataFrame, threshold: float, tokens: int):
    """phrases(text, lang): chunk_no, start, phrase of a text's greedy segmentation by frozen counts (n, phrase, cnt). They travel with
    the function, so there may be at most SHIPPED; for more, segment by ``operators.segment.partition``."""
    from ..operators.segment import merge_chunk

    if counts.count() > SHIPPED:
        raise ValueError(f"over {SHIPPED} phrases: use operators.segment.partition")
    known = {r["phrase"]: r["cnt"] for r in counts.select("phrase", "cnt").toLocalIterator()}
    longest = max((p.count(" ") + 1 for p in known), default=1)

    @udtf(returnType="chunk_no int, start int, phrase string")
    class Phrases:
        def eval(self, text: str, lang: str):
            stop = set(STOP_WORDS.get(lang, ()))
            for no, part in enumerate(_BOUNDARY.split((text or "").lower())):
                toks = [w for w in _GAP.split(part) if w and w not in stop]
                if toks:
                    spans = {(i, m): c for i in range(len(toks)) for m in range(1, min(longest, len(toks) - i) + 1) if (c := known.get(" ".join(toks[i : i + m])))}
                    for at, n in merge_chunk(len(toks), spans, threshold, tokens)[0]:
                        yield no, at, " ".join(toks[at : at + n])

    return Phrases


@udtf(returnType="pos int, phrase string")
class Ngrams:
    """ngrams(tokens, n): position and text of every contiguous run of n tokens."""

    def eval(self, tokens: list, n: int):
        for i in range(len(tokens or ()) - n + 1):
            yield i, " ".join(tokens[i : i + n])


@udtf(returnType="chunk_no int, pos int, word string, kept boolean")
class Words:
    """phrase_words(text, lang): the tokens of every chunk of a text, and whether the language's stop list keeps them."""

    def eval(self, text: str, lang: str):
        stop = set(STOP_WORDS.get(lang, ()))
        for no, part in enumerate(_BOUNDARY.split((text or "").lower())):
            for pos, word in enumerate(filter(None, _GAP.split(part))):
                yield no, pos, word, word not in stop


def register(spark: SparkSession, known: DataFrame | None = None, threshold: float = 3.0, tokens: int = 1) -> None:
    """The functions of this module; with counts (phrase, cnt) of a mined corpus of ``tokens`` tokens also phrases(text, lang)."""
    spark.udtf.register("ngrams", Ngrams)
    spark.udtf.register("phrase_words", Words)
    if known is not None:
        spark.udtf.register("phrases", phrases_function(known, threshold, tokens))
    # SQL functions are expanded into the plan, so they run in generated code
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION phrase_sig(f1 DOUBLE, f2 DOUBLE, f12 DOUBLE, tokens DOUBLE) RETURNS DOUBLE RETURN (f12 - f1 * f2 / tokens) / sqrt(f12)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION phrase_key(phrase STRING) RETURNS STRING RETURN array_join(array_sort(split(phrase, ' ')), ' ')")
