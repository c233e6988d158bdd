"""URL filters: host and path rules first, else logistic regression on hashed character n-grams.

The regression is trained in numpy from a small table of labelled URLs (1: block). Host and path n-grams are hashed apart.

The regression knows words by their n-grams: it blocks what shares them with the table's blocked hosts or paths, and a word
unlike any in the table is no evidence.

Edge cases: a null URL or one without ``://`` has an empty host and path, fits no rule and gets the verdict of the empty
feature set; very long URLs are read whole; repeated rows are judged each, null ids too; an empty table gives no rows; without
any labelled URL all is allowed (score 0.5 is under no bound of 0.5, so the bound is passed strictly); other columns are
not read, whatever their names.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_rows

DIM, GRAMS = 1 << 18, (3, 4, 5)


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str

    @property
    def text(self) -> str:
        return self.host + self.path


def parts(url: str | Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a URL column."""
    url = F.col(url) if isinstance(url, str) else url
    found = F.coalesce(F.locate("://", url), F.lit(0))
    rest = F.when(found > 0, F.substring(url, found + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    path = F.regexp_extract(F.substring(rest, F.length(host) + 1, F.length(rest)), r"^([^?#]*)", 1)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def match(host: Column, path: Column, rules: list[Rule]) -> tuple[Column, Column]:
    """Text and verdict of the longest rule that fits host and path; nulls if none does."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: len(r.text)):
        fits = ((host == r.host) | F.endswith(host, F.lit("." + r.host))) & F.startswith(path, F.lit(r.path))
        name, verdict = F.when(fits, F.lit(r.text)).otherwise(name), F.when(fits, F.lit(r.verdict)).otherwise(verdict)
    return name, verdict


def features(host: str, path: str) -> np.ndarray:
    out = []
    for mark, s in (("h", host), ("p", path)):
        s = f"^{s}$"
        out += [zlib.crc32(f"{mark}{s[i:i + n]}".encode()) % DIM for n in GRAMS for i in range(len(s) - n + 1)]
    return np.unique(np.array(out, np.int64))


@dataclass
class Model:
    weights: np.ndarray
    bias: float

    def score(self, host: str, path: str) -> float:
        f = features(host, path)
        return 1 / (1 + float(np.exp(-np.clip(self.weights[f].sum() / np.sqrt(max(1, len(f))) + self.bias, -50, 50))))


def split(url: str) -> tuple[str, str]:
    """Host and path of one URL of the training table, as ``parts`` gives them."""
    _, mark, rest = url.partition("://")
    cut = min((rest.find(c) for c in "/?#" if c in rest), default=len(rest))
    path = rest[cut:] if mark else ""
    return (rest[:cut].translate({i: i + 32 for i in range(65, 91)}) if mark else ""), path[: min((path.find(c) for c in "?#" if c in path), default=len(path))]


def train(labelled: list[tuple[str, str, int]], epochs: int = 40, rate: float = 0.5, decay: float = 1e-4, seed: int = 3) -> Model:
    """labelled: host, path, 1 to block or 0."""
    data, rng = [(features(h, p), y) for h, p, y in labelled], np.random.default_rng(seed)
    blocked = sum(y for *_, y in labelled)
    # the shares of the labels, held fixed, so that a URL without evidence gets the more common verdict
    model = Model(np.zeros(DIM), float(np.log((1 + blocked) / (1 + len(labelled) - blocked))))
    for epoch in range(epochs):
        step = rate / (1 + epoch / 20)
        for i in rng.permutation(len(data)):
            f, y = data[i]
            size = np.sqrt(max(1, len(f)))
            error = 1 / (1 + np.exp(-np.clip(model.weights[f].sum() / size + model.bias, -50, 50))) - y
            model.weights[f] -= step * (error / size + decay * model.weights[f])
    return model


def judge(pages: DataFrame, rules: list[Rule], model: Model, id_col: str = "page_id", url_col: str = "url", bound: float = 0.5) -> DataFrame:
    """id, host, path, rule, verdict (allow or block), block_score (the regression's, for every row)."""
    host, path = parts(F.col(url_col).cast("string"))
    rows = pages.select(F.col(id_col).cast("long").alias(id_col), host.alias("host"), path.alias("path"))

    def make():
        return lambda ids, hosts, paths: {id_col: ids, "host": hosts, "path": paths, "block_score": [model.score(h, p) for h, p in zip(hosts, paths, strict=True)]}

    scored = map_rows(rows, make, f"{id_col} long, host string, path string, block_score double")
    rule, verdict = match(F.col("host"), F.col("path"), rules)
    learned = F.when(F.col("block_score") > bound, "block").otherwise("allow")
    return scored.select(id_col, "host", "path", rule.alias("rule"), F.coalesce(verdict, learned).alias("verdict"), "block_score")
