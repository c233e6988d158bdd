"""Greedy significance-guided segmentation of chunks into phrases.

In every chunk the best-scored adjacent pair of units merges while its score reaches the threshold. The order is global in a
chunk and free between chunks, so distinct chunks are segmented once and in parallel, and chunks without a frequent pair never
leave the JVM.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.io import settle
from .mining import Mined

#: Scores are compared and ranked after rounding to so many digits, in every engine.
DIGITS = 9


def expected(f1: Column, f2: Column, tokens: int) -> Column:
    """Mean count of two units side by side if they were independent."""
    return f1 * f2 / F.lit(float(tokens))


def score(f1: Column, f2: Column, f12: Column, tokens: int, kind: str = "std", mean: Column | None = None) -> Column:
    """How far a pair's count lies over its mean: in standard deviations of the sample ('std'; for two words the t statistic),
    of the binomial law ('binomial_var'), or of the independent model ('null_var'). ``mean`` replaces the model's mean."""
    size = F.lit(float(tokens))
    mu = expected(f1, f2, tokens) if mean is None else mean
    spread = {"std": F.sqrt(f12), "binomial_var": F.sqrt(f12 * (1 - f12 / size)), "null_var": F.sqrt(mu)}[kind]
    return (f12 - mu) / spread


def score_value(f1: float, f2: float, f12: float, tokens: int) -> float:
    return round((f12 - f1 * f2 / tokens) / math.sqrt(f12), DIGITS)


class Spans:
    """Counts of a chunk's frequent spans: for each start those of one word, two words and so on, as what begins a frequent phrase
    is frequent."""

    def __init__(self, ats: list[int], ends: list[int], flat: np.ndarray | list[int]) -> None:
        self.rows = {at: (a, b - a) for at, a, b in zip(ats, ends, ends[1:], strict=False)}
        self.flat = flat

    def get(self, span: tuple[int, int]) -> int | None:
        first, most = self.rows.get(span[0], (0, 0))
        return self.flat[first + span[1] - 1] if span[1] <= most else None

    def __getitem__(self, span: tuple[int, int]) -> int:
        return self.flat[self.rows[span[0]][0] + span[1] - 1]


def merge_chunk(size: int, counts: Spans | dict[tuple[int, int], int], threshold: float, tokens: int, scorer=None) -> tuple[list[tuple[int, int]], list[tuple[int, int, int, float]]]:
    """Units (start, length) of a chunk of ``size`` tokens and its merges (start, left length, right length, score).

    ``counts`` has the frequent spans (start, length). Units form a linked list; a heap holds the mergeable pairs, and pairs that
    a merge has overtaken are skipped when they come up."""
    length, after, before = [1] * size, list(range(1, size + 1)), list(range(-1, size - 1))
    heap: list[tuple[float, int, int, int]] = []

    def offer(left: int) -> None:
        right = after[left]
        if left < 0 or right >= size:
            return
        both = counts.get((left, length[left] + length[right]))
        if both is None:
            return
        if scorer:
            s = scorer(left, length[left], length[right])
        else:
            s = score_value(counts[left, length[left]], counts[right, length[right]], both, tokens)
        if s is not None and s >= threshold:
            heapq.heappush(heap, (-s, left, length[left], length[right]))

    for i in range(size - 1):
        offer(i)
    alive, merges = [True] * size, []
    while heap:
        s, left, a, b = heapq.heappop(heap)
        right = left + a
        if not alive[left] or length[left] != a or right >= size or not alive[right] or length[right] != b:
            continue
        merges.append((left, a, b, -s))
        alive[right], length[left], after[left] = False, a + b, after[right]
        if after[right] < size:
            before[after[right]] = left
        offer(left)
        if before[left] >= 0:
            offer(before[left])
    units, i = [], 0
    while i < size:
        units.append((i, length[i]))
        i = after[i]
    return units, merges


def _spans(mined: Mined) -> DataFrame:
    """For each distinct chunk with a frequent pair: uid, size, spans array<struct<at, cnts>>, cnts being the counts of one word and
    more from ``at`` on. Words that no frequent pair holds are never merged, so their counts are left out."""
    multi = mined.spans.select("uid", "at", "n", "cnt")
    pairs = multi.where("n = 2").select("uid", F.explode(F.array("at", F.col("at") + 1)).alias("at")).groupBy("uid").agg(F.collect_set("at").alias("ats"))
    chunks = mined.chunks.select("uid", "toks").join(pairs, "uid").select("uid", F.size("toks").alias("size"), F.explode(F.transform("ats", lambda i: F.struct(i.alias("at"), F.get("toks", i).alias("word")))).alias("t"))
    words = chunks.select("uid", "size", "t.at", "t.word").join(mined.counts.where("n = 1").select(F.col("phrase").alias("word"), "cnt"), "word")
    # one exchange by chunk for both; a chunk's spans are put in order within its row
    rows = words.select("uid", "size", "at", F.lit(1).alias("n"), "cnt").unionByName(multi.withColumn("size", F.lit(0)))
    return rows.groupBy("uid").agg(F.max("size").alias("size"), F.sort_array(F.collect_list(F.struct("at", "n", "cnt"))).alias("flat"))


def nested(spans: DataFrame) -> DataFrame:
    """The flat spans (at, n, cnt) of each chunk by start, as the expression kernel looks them up."""
    starts = F.filter("flat", lambda x: x["n"] == 1)
    return spans.select("uid", "size", F.transform(starts, lambda s: F.struct(s["at"].alias("at"), F.transform(F.filter("flat", lambda x: x["at"] == s["at"]), lambda x: x["cnt"]).alias("cnts"))).alias("spans"))


UNITS = "uid long, units array<struct<at: int, len: int>>, merges array<struct<at: int, left: int, right: int, sig: double>>"
#: Chunks, and counts of a chunk, that are Python objects at one time.
SLICE, FEW_COUNTS = 512, 100_000


def _heap_kernel(threshold: float, tokens: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for begin in range(0, whole.num_rows, SLICE):
                batch = whole.slice(begin, SLICE)
                uids, units, merges = batch.column(0), [], []
                spans = batch.column(2)
                inner, begin_of = spans.flatten(), 0
                at, flat = (inner.field(i).to_numpy(zero_copy_only=False) for i in (0, 2))
                heads = np.flatnonzero(inner.field(1).to_numpy(zero_copy_only=False) == 1)
                for size, n in zip(batch.column(1).to_pylist(), pc.list_value_length(spans).to_pylist(), strict=True):
                    values = flat[begin_of : begin_of + n]
                    own = heads[slice(*np.searchsorted(heads, [begin_of, begin_of + n]))]
                    u, m = merge_chunk(size, Spans(at[own].tolist(), [*(own - begin_of).tolist(), n], values.tolist() if len(values) < FEW_COUNTS else values), threshold, tokens)
                    begin_of += n
                    units.append([{"at": a, "len": k} for a, k in u])
                    merges.append([{"at": a, "left": x, "right": y, "sig": s} for a, x, y, s in m])
                yield pa.RecordBatch.from_arrays([uids, pa.array(units, pa.list_(pa.struct([("at", pa.int32()), ("len", pa.int32())]))), pa.array(merges, pa.list_(pa.struct([("at", pa.int32()), ("left", pa.int32()), ("right", pa.int32()), ("sig", pa.float64())])))], ["uid", "units", "merges"])

    return run


def expression_kernel(spans: DataFrame, threshold: float, tokens: int) -> DataFrame:
    """The same units in built-in functions only: one fold step a possible merge. Quadratic in the chunk, so for short chunks."""
    key = lambda at, n: at * 1024 + n
    table = F.map_from_entries(F.flatten(F.transform("spans", lambda s: F.transform(s["cnts"], lambda c, i: F.struct(key(s["at"], i + 1).alias("k"), c.cast("double").alias("v"))))))
    unit = "array<struct<at:int,len:int>>"
    first = F.transform(F.sequence(F.lit(0), F.col("size") - 1), lambda i: F.struct(i.alias("at"), F.lit(1).alias("len"))).cast(unit)

    def step(units: Column, _: Column) -> Column:
        pair = lambda i: (F.get(units, i), F.get(units, i + 1))

        def rated(i: Column) -> Column:
            a, b = pair(i)
            f12, f1, f2 = (F.element_at("table", k) for k in (key(a["at"], a["len"] + b["len"]), key(a["at"], a["len"]), key(b["at"], b["len"])))
            return F.struct(F.round(score(f1, f2, f12, tokens), DIGITS).alias("sig"), (-i).alias("minus"))

        rates = F.filter(F.transform(F.sequence(F.lit(0), F.size(units) - 2), rated), lambda r: r["sig"].isNotNull() & (r["sig"] >= threshold))
        best = F.array_max(rates)["minus"]
        at = -best
        joined = F.transform(F.filter(F.transform(units, lambda u, i: F.struct(u["at"].alias("at"), F.when(i == at, u["len"] + F.get(units, at + 1)["len"]).otherwise(u["len"]).alias("len"), i.alias("i"))), lambda u: u["i"] != at + 1), lambda u: F.struct(u["at"].alias("at"), u["len"].alias("len")))
        return F.when((F.size(units) < 2) | best.isNull(), units).otherwise(joined).cast(unit)

    steps = F.sequence(F.lit(1), F.greatest(F.col("size") - 1, F.lit(1)))
    return spans.withColumn("table", table).select("uid", F.aggregate(steps, first, step).alias("units"))


def segment_unique(mined: Mined, threshold: float, kernel: str = "heap") -> DataFrame:
    """uid, toks, mult, units, merges of every distinct chunk; chunks without a frequent pair are single words without any work."""
    spans = _spans(mined)
    done = expression_kernel(nested(spans), threshold, mined.tokens).withColumn("merges", F.array().cast("array<struct<at:int,left:int,right:int,sig:double>>")) if kernel == "expr" else spans.select("uid", "size", "flat").mapInArrow(_heap_kernel(threshold, mined.tokens), UNITS)
    single = F.transform("toks", lambda t, i: F.struct(i.cast("int").alias("at"), F.lit(1).alias("len")))
    return mined.chunks.join(done, "uid", "left").select("uid", "toks", "mult", F.coalesce("units", single).alias("units"), "merges")


def phrase_of(toks: Column, unit: Column) -> Column:
    return F.concat_ws(" ", F.slice(toks, unit["at"] + 1, unit["len"]))


def partition(chunks: DataFrame, mined: Mined, threshold: float, kernel: str = "heap") -> DataFrame:
    """doc_id, chunk_no, g (order in the document, from 0), start, len, phrase: every document as a sequence of phrases."""
    # written, so that the exchanges of the segmentation are gone before those below begin
    units = settle(segment_unique(mined, threshold, kernel).select(F.col("toks").alias("u_toks"), F.transform("units", lambda u: u["at"]).alias("ats")), "units")
    rows = chunks.select("doc_id", "chunk_no", "toks").join(units, F.col("toks") == F.col("u_toks")).select("doc_id", "chunk_no", "toks", "ats")
    # a chunk's place in its document is added up over chunks, and its phrases are listed after that
    before = Window.partitionBy("doc_id").orderBy("chunk_no").rowsBetween(Window.unboundedPreceding, -1)
    placed = rows.withColumn("first", F.coalesce(F.sum(F.size("ats")).over(before), F.lit(0)).cast("int"))
    unit = F.transform("ats", lambda at, i: F.struct(at.alias("at"), (F.coalesce(F.get("ats", i + 1), F.size("toks")) - at).alias("len")))
    listed = placed.select("doc_id", "chunk_no", "toks", "first", F.posexplode(unit).alias("i", "unit"))
    return listed.select("doc_id", "chunk_no", F.col("unit.at").alias("start"), F.col("unit.len").alias("len"), phrase_of(F.col("toks"), F.col("unit")).alias("phrase"), (F.col("first") + F.col("i")).alias("g"))


def trace(mined: Mined, threshold: float) -> DataFrame:
    """Merges of each distinct chunk in order: chunk, mult, step, left_phrase, right_phrase, sig."""
    rows = segment_unique(mined, threshold).select(F.concat_ws(" ", "toks").alias("chunk"), "toks", "mult", F.posexplode("merges").alias("step", "m"))
    cut = lambda at, n: F.concat_ws(" ", F.slice("toks", at + 1, n))
    return rows.select("chunk", "mult", (F.col("step") + 1).alias("step"), cut(F.col("m.at"), F.col("m.left")).alias("left_phrase"), cut(F.col("m.at") + F.col("m.left"), F.col("m.right")).alias("right_phrase"), F.col("m.sig").alias("sig"))


def bag(parts: DataFrame) -> DataFrame:
    """phrase, n_words, cnt: instances after the partition, which is a phrase's rectified frequency."""
    return parts.groupBy("phrase", F.col("len").alias("n_words")).agg(F.count("*").alias("cnt"))


def bag_unique(mined: Mined, threshold: float) -> DataFrame:
    """The same from distinct chunks and their multiplicities, without going back to documents."""
    rows = segment_unique(mined, threshold).select("toks", "mult", F.explode("units").alias("unit"))
    return rows.groupBy(phrase_of(F.col("toks"), F.col("unit")).alias("phrase"), F.col("unit.len").alias("n_words")).agg(F.sum("mult").alias("cnt"))


def rejected(counts: DataFrame, bagged: DataFrame) -> DataFrame:
    """Frequent candidates of two words or more that no partition uses: phrase, raw_cnt."""
    return counts.where("n > 1").join(bagged.select("phrase"), "phrase", "left_anti").select("phrase", F.col("cnt").alias("raw_cnt"))


def check_partition(parts: DataFrame, chunks: DataFrame) -> DataFrame:
    """Chunks whose phrases don't concatenate to their tokens; none if the partition is valid."""
    joined = parts.groupBy("doc_id", "chunk_no").agg(F.concat_ws(" ", F.transform(F.array_sort(F.collect_list(F.struct("start", "phrase"))), lambda x: x["phrase"])).alias("rebuilt"))
    whole = chunks.select("doc_id", "chunk_no", F.concat_ws(" ", "toks").alias("source"))
    return whole.join(joined, ["doc_id", "chunk_no"], "full").where(~F.col("source").eqNullSafe(F.col("rebuilt")))
