"""Language identification: averaged embeddings of hashed subwords and a linear softmax, trained by SGD in numpy.

A text's letters are lower-cased, everything else becomes one blank; its runs of 1 to 4 characters, blanks included, are
hashed to buckets. The mean of the buckets' embeddings goes through a linear layer. Training takes a bounded sample of
labelled rows, ``per_language`` expected for each language (of their whole texts). A tenth of the sample is kept for calibration: a
temperature for the scores, and the rejection bound, under which that share of good texts lies that may be lost.

Edge cases: null text, or text without a letter, is ``und`` with score 0 and rejected; a null label is not learned from;
without any labelled row everything is ``und``; very long texts are read whole; repeated rows are judged each, null ids too; an
empty table gives no rows; other columns than those asked for are not read, whatever their names.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_rows

BUCKETS, WIDTH, SIZES = 1 << 15, 16, (1, 2, 3, 4)
#: Rows of each language that training may collect, and the share of good texts that rejection may cost.
PER_LANGUAGE, LOST = 1500, 0.0005
_FACTORS = np.array([0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F], dtype=np.uint32)


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)


def subwords(text: str | None) -> np.ndarray:
    """Buckets of all subwords of the text; empty if it has no letter."""
    codes = np.frombuffer((text or "").lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    codes = np.where(_letters()[codes], codes, np.uint32(32))
    codes = np.concatenate([[np.uint32(32)], codes, [np.uint32(32)]]).astype(np.uint32)
    codes = codes[(codes != 32) | (np.concatenate([[True], codes[:-1] != 32]))]
    if len(codes) <= 1:
        return np.zeros(0, np.int64)
    out = []
    for n in SIZES:
        if len(codes) >= n:
            h = np.full(len(codes) - n + 1, n, np.uint32)
            for i in range(n):
                h = (h ^ codes[i : len(codes) - n + 1 + i]) * _FACTORS[i]
                h ^= h >> np.uint32(15)
            out.append(h & np.uint32(BUCKETS - 1))
    return np.concatenate(out).astype(np.int64)


@dataclass
class Model:
    languages: list[str]
    table: np.ndarray  # bucket x language: embedding times linear layer
    bias: np.ndarray
    temperature: float
    reject_below: float

    def logits(self, buckets: np.ndarray) -> np.ndarray:
        return self.table[buckets].mean(0) + self.bias

    def judge(self, text: str | None) -> tuple[str, float, bool]:
        """Language, calibrated probability, rejected?"""
        buckets = subwords(text)
        if not len(buckets) or not self.languages:
            return "und", 0.0, True
        p = _softmax(self.logits(buckets) / self.temperature)
        k = int(p.argmax())
        return self.languages[k], float(p[k]), bool(p[k] < self.reject_below)


def _softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def train(samples: list[tuple[np.ndarray, np.ndarray, str]], epochs: int = 4, rate: float = 2.0, seed: int = 1) -> Model:
    """samples: distinct buckets, their counts, language."""
    samples = [s for s in samples if len(s[0])]
    languages = sorted({s[2] for s in samples})
    if not languages:
        return Model([], np.zeros((BUCKETS, 0)), np.zeros(0), 1.0, 0.0)
    rng = np.random.default_rng(seed)
    number = {x: i for i, x in enumerate(languages)}
    embed = rng.normal(0, 1 / WIDTH, (BUCKETS, WIDTH))
    layer, bias = np.zeros((WIDTH, len(languages))), np.zeros(len(languages))
    order = rng.permutation(len(samples))
    held = order[: len(order) // 10]
    learn = order[len(order) // 10 :]
    steps, done = epochs * len(learn), 0
    for _ in range(epochs):
        for i in rng.permutation(learn):
            buckets, counts, lang = samples[i]
            share = (counts / counts.sum())[:, None]
            hidden = (embed[buckets] * share).sum(0)
            error = _softmax(hidden @ layer + bias)
            error[number[lang]] -= 1
            step = rate * (1 - done / steps)
            back = layer @ error
            layer -= step * np.outer(hidden, error)
            bias -= 0.1 * step * error
            embed[buckets] -= step * share * back * min(20, len(buckets))  # few of a text's many buckets move far at its mean's rate
            done += 1
    model = Model(languages, embed @ layer, bias, 1.0, 0.0)
    check = held if len(held) >= 20 else order
    logits = np.stack([(model.table[b] * (c / c.sum())[:, None]).sum(0) + bias for b, c, _ in (samples[i] for i in check)])
    truth = np.array([number[samples[i][2]] for i in check])
    heats = np.geomspace(0.05, 20, 60)
    losses = [-np.log(_softmax(logits / t)[np.arange(len(truth)), truth] + 1e-12).mean() for t in heats]
    model.temperature = float(heats[int(np.argmin(losses))])
    right = _softmax(logits / model.temperature)
    good = np.sort(right.max(1)[right.argmax(1) == truth])
    # never stricter than an even guess between the two best languages
    model.reject_below = float(min(0.5, good[int(LOST * len(good))])) if len(good) else 0.0
    return model


def fit(docs: DataFrame, learn_from: Column, per_language: int = PER_LANGUAGE, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model:
    """Train on a share of the rows of each language, per_language expected, among docs where learn_from holds. A hash of id and text
    deals the rows, so the same table gives the same model however it is cut into files. Features are made where the texts are."""
    text = F.col(text_col).cast("string")
    rows = docs.where(learn_from & F.col(lang_col).isNotNull()).select(text.alias("text"), F.col(lang_col).cast("string").alias("lang"), F.pmod(F.xxhash64(F.lit("language"), F.col(id_col).cast("long"), text), F.lit(1 << 30)).alias("dealt"))
    sizes = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().collect()}  # a row a language
    if not sizes:
        return train([])
    # the id is in the hash, so that copies of one text do not all come at once
    share = F.lit(0.0)
    for lang, n in sizes.items():
        share = F.when(F.col("lang") == lang, min(1.0, per_language / n)).otherwise(share)

    def make():
        def work(texts, langs):
            found = [np.unique(subwords(t), return_counts=True) for t in texts]
            # counts take two bytes where they fit, which the lengths tell
            return {"lang": langs, "buckets": [b.astype("<u2").tobytes() for b, _ in found], "counts": [c.astype("<u2" if c.max(initial=0) < 1 << 16 else "<u4").tobytes() for _, c in found]}

        return work

    table = map_rows(rows.where(F.col("dealt") < share * (1 << 30)).select("text", "lang"), make, "lang string, buckets binary, counts binary").toArrow()
    samples = []
    for batch in table.to_batches():
        buckets, counts = (_views(batch.column(i)) for i in (1, 2))
        samples += [(b.view("<u2"), c.view("<u2" if len(c) == len(b) else "<u4"), lang) for b, c, lang in zip(buckets, counts, batch.column(0).to_pylist(), strict=True)]
    model = train(sorted(samples, key=lambda s: (s[2], len(s[0]), s[0].tobytes(), s[1].tobytes())))
    del samples, table
    pa.default_memory_pool().release_unused()
    return model


def _views(column: pa.Array) -> list[np.ndarray]:
    """The bytes of each value of a binary column, without a copy."""
    _, offsets, data = column.buffers()
    ends = np.frombuffer(offsets, np.int32)[column.offset : column.offset + len(column) + 1]
    flat = np.frombuffer(data, np.uint8) if data else np.zeros(0, np.uint8)
    return [flat[a:b] for a, b in zip(ends.tolist(), ends[1:].tolist(), strict=False)]


def predict(docs: DataFrame, model: Model, keep: list[str], text_col: str = "text") -> DataFrame:
    """The columns ``keep`` of docs with lang_pred, score and rejected."""
    rows = docs.select(*[F.col(c) for c in keep], F.col(text_col).cast("string").alias("judged_text"))
    names = rows.columns
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[:-1])

    def run(batches):
        for batch in batches:
            got = [model.judge(t.as_py()) for t in batch.column(len(names) - 1)]
            cols = [batch.column(i) for i in range(len(names) - 1)]
            yield pa.RecordBatch.from_arrays([*cols, pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64()), pa.array([g[2] for g in got], pa.bool_())], [*names[:-1], "lang_pred", "score", "rejected"])

    return rows.mapInArrow(run, ", ".join(x for x in (schema, "lang_pred string, score double, rejected boolean") if x))
