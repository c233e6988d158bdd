"""Approximate nearest neighbours by cosine: an inverted file of coarse centroids with product-quantised residuals.

Centroids and residual codebooks are fitted in numpy on a bounded sample (``SAMPLE`` rows, chosen by a hash of the id);
every row is indexed. A query visits its nearest lists; there an asymmetric table (its inner products with all codewords)
scores the codes. The best ``rerank`` codes of a tile get the exact cosine of the original vectors, and after them every
code that may still be above the k-th of these: its estimate is off by at most ``reach`` times its own error. A list longer
than ``TILE_ROWS`` is cut into tiles, as are the queries that visit it, so no list is one task's work.

How many lists to probe, and the reach, are measured: ``ASKED`` of the queries themselves, chosen by a hash, are compared with
all rows (one pass, linear in the rows). The probes hold ``TARGET`` of these true neighbours and the reach ``SURE`` of them, so
neither rests on how alike queries and rows are, nor on how tight the groups of vectors lie.

Vectors meet vectors of their own length. The most frequent length, and others with over ``FEW`` vectors (at most ``INDEXES``
lengths), have an index each; the vectors of rarer lengths are compared with each other exactly, in tiles.

Edge cases: vectors that are null, empty, zero, or hold null or non-finite components take no part; components of any size are scaled
by powers of two, so their squares neither overflow nor vanish; rows repeating an id and a
vector count once; a query is never its own candidate (by id); ties go to the smaller id; probes go on until they hold more
than k rows, so small tables return all candidates; an empty table gives no rows; other columns are not read, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import settle
from .vectors import best, matrix, once, usable

SAMPLE, MOST_LISTS = 20_000, 1024
ASKED, TARGET, SURE = 400, 0.97, 0.995
TILE_ROWS, TILE_QUERIES = 4_096, 2_048
WORDS, PART = 256, 4
FEW, INDEXES = 4_096, 16


def lloyd(x: np.ndarray, k: int, rounds: int, rng: np.random.Generator) -> np.ndarray:
    centres = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        near = np.argmin((centres**2).sum(1)[None, :] - 2 * x @ centres.T, axis=1)
        sums, n = np.zeros_like(centres), np.bincount(near, minlength=len(centres))
        np.add.at(sums, near, x)
        centres[n > 0] = sums[n > 0] / n[n > 0, None]
    return centres


@dataclass
class Index:
    """What a task needs to place and score vectors; its size depends on parameters, not on the data."""

    centres: np.ndarray
    books: list[np.ndarray]
    cuts: list[np.ndarray]
    probes: int = 1
    reach: float = 1.0

    def lists(self, unit: np.ndarray) -> np.ndarray:
        return np.argmin((self.centres**2).sum(1)[None, :] - 2 * unit @ self.centres.T, axis=1)

    def codes(self, unit: np.ndarray, lists: np.ndarray) -> np.ndarray:
        rest = unit - self.centres[lists]
        return np.stack([np.argmin((b**2).sum(1)[None, :] - 2 * rest[:, c] @ b.T, axis=1) for b, c in zip(self.books, self.cuts, strict=True)], 1).astype(np.uint8)

    def decoded(self, codes: np.ndarray) -> np.ndarray:
        """The residuals that the codes stand for."""
        return np.concatenate([b[codes[:, m]] for m, b in enumerate(self.books)], 1)

    def order(self, unit: np.ndarray) -> np.ndarray:
        return np.argsort((self.centres**2).sum(1)[None, :] - 2 * unit @ self.centres.T, axis=1, kind="stable")


def fit(sample: np.ndarray, lists: int, seed: int = 7) -> Index:
    rng = np.random.default_rng(seed)
    unit = units(sample)
    cuts = np.array_split(np.arange(unit.shape[1]), max(1, unit.shape[1] // PART))
    index = Index(lloyd(unit, lists, 10, rng), [], cuts)
    rest = unit - index.centres[index.lists(unit)]
    index.books = [lloyd(rest[:, c], WORDS, 6, rng) for c in cuts]
    return index


def measure(index: Index, placed: DataFrame, is_query: Column, k: int) -> None:
    """Set the index's probes and reach by the true neighbours of some of the queries among all rows placed."""
    some = placed.where(is_query).select("id", "vec").orderBy(F.xxhash64("id", F.lit(5)), "id").limit(ASKED).toArrow()
    if not len(some):
        return
    asked_ids, asked = some.column("id").to_numpy(), units(matrix(some.column("vec")))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The k nearest rows of the task for each query asked."""
        names = ["query", "id", "score", "list", "off"]
        held: list[list[tuple[np.ndarray, ...]]] = [[] for _ in asked_ids]
        for batch in batches:
            for start in range(0, batch.num_rows, TILE_ROWS):
                ids, vec, home, codes, err = batch.slice(start, TILE_ROWS).columns
                ids, home, err, unit = ids.to_numpy(), home.to_numpy(), err.to_numpy(), units(matrix(vec))
                known = index.centres[home] + index.decoded(np.frombuffer(b"".join(codes.to_pylist()), np.uint8).reshape(len(ids), -1))
                scores = asked @ unit.T
                for i, own in enumerate(asked_ids):
                    near = best(ids, np.where(ids == own, -np.inf, scores[i]), k)
                    near = near[ids[near] != own]
                    off = (scores[i, near] - known[near] @ asked[i]) / np.maximum(err[near], 1e-12)
                    held[i].append((ids[near], scores[i, near], home[near], off))
        for i, parts in enumerate(held):
            if parts:
                ids, scores, home, off = (np.concatenate(x) for x in zip(*parts, strict=True))
                top = best(ids, scores, k)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(top), i, np.int32)), *(pa.array(x[top]) for x in (ids, scores, home, off))], names)

    near = placed.select("id", "vec", "list", "codes", "err").mapInArrow(compare, "query int, id long, score double, list int, off double").dropDuplicates(["query", "id", "score"])
    rank = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("score"), "id"))
    # k rows for each query asked
    true = near.withColumn("rank", rank).where(F.col("rank") <= k).toArrow()
    if len(true):
        place = np.argsort(index.order(asked), axis=1)
        found = np.sort(place[true.column("query").to_numpy(), true.column("list").to_numpy()])
        off = np.sort(true.column("off").to_numpy())
        index.probes = int(found[min(len(found) - 1, int(TARGET * len(found)))]) + 1
        index.reach = float(np.clip(off[min(len(off) - 1, int(SURE * len(off)))], 0, 1))


def scaled(x: np.ndarray) -> np.ndarray:
    """Rows times powers of two that bring their largest component to between 0.5 and 1."""
    return np.ldexp(x, -np.frexp(np.abs(x).max(1, keepdims=True))[1]) if len(x) else x


def units(x: np.ndarray) -> np.ndarray:
    x = scaled(x)
    return x / np.linalg.norm(x, axis=1, keepdims=True) if len(x) else x


def exact_cosines(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Row by row in one order of summation, so equal vectors have equal scores wherever they lie."""
    return (x * q).sum(1) / (np.sqrt((x * x).sum(1)) * np.sqrt((q * q).sum()))


def nearest(rows: DataFrame, is_query: Column, k: int = 5, rerank: int = 128, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """query_id, rank (from 1), the candidate's id under id_col's name, score (cosine) of the k nearest found for each row where
    is_query, a condition on column ``id``, holds."""
    good = usable(rows, id_col, vec_col, nonzero=True)
    sizes = good.groupBy(F.size("vec").alias("dim")).count()
    dims = sizes.orderBy(F.desc("count"), "dim").limit(INDEXES).collect()
    dims = [r for i, r in enumerate(dims) if i == 0 or r["count"] > FEW]
    tops = [_indexed(good.where(F.size("vec") == r["dim"]), r["count"], is_query, k, rerank) for r in dims]
    rest = good.where(~F.size("vec").isin([r["dim"] for r in dims])) if dims else good
    if not dims or sizes.count() > len(dims):
        tops.append(_compared(rest, is_query, k))
    found = tops[0]
    for t in tops[1:]:
        found = found.unionByName(t)
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), F.col("id").alias(id_col), "score")


def _compared(good: DataFrame, is_query: Column, k: int) -> DataFrame:
    """query_id, id, score of the k nearest in each tile, by all cosines within a length."""
    n, n_q = (v or 0 for v in good.agg(F.count("*"), F.sum(is_query.cast("long"))).first())
    tiles, q_tiles = max(1, -(-n // TILE_ROWS)), max(1, -(-n_q // TILE_QUERIES))
    every = lambda count: F.explode(F.sequence(F.lit(0), F.lit(count - 1)))
    mine = lambda count: F.pmod(F.xxhash64("id"), F.lit(count)).cast("int")
    left = good.where(is_query).select(F.size("vec").alias("dim"), every(tiles).alias("tile"), mine(q_tiles).alias("q_tile"), "id", "vec")
    right = good.select(F.size("vec").alias("dim"), mine(tiles).alias("tile"), every(q_tiles).alias("q_tile"), "id", "vec")
    keys = ["dim", "tile", "q_tile"]

    def run(queries: pa.Table, candidates: pa.Table) -> pa.Table:
        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        if len(queries) and len(candidates):
            sides = []
            for t in (queries, candidates):
                ids, x = t.column("id").to_numpy(), matrix(t.column("vec"))
                keep = once(ids, x)
                sides.append((ids[keep], scaled(x[keep])))
            (q_ids, q), (ids, x) = sides
            for i in range(len(q_ids)):
                near = np.flatnonzero(ids != q_ids[i])
                scores = exact_cosines(q[i], x[near])
                top = best(ids[near], scores, k)
                out.append((np.full(len(top), q_ids[i]), ids[near[top]], scores[top]))
        cols = [np.concatenate(c) for c in zip(*out, strict=True)]
        return pa.table({"query_id": cols[0], "id": cols[1], "score": cols[2]})

    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(run, "query_id long, id long, score double")


def _indexed(good: DataFrame, n: int, is_query: Column, k: int, rerank: int) -> DataFrame:
    """query_id, id, score of the k nearest in each tile of the lists that a query visits; vectors of one length."""
    spark = good.sparkSession
    share = min(1.0, 1.1 * SAMPLE / n)
    taken = good.where(F.pmod(F.xxhash64("id", F.lit(11)), F.lit(1 << 30)) < F.lit(int(share * (1 << 30)))) if share < 1 else good
    sample = matrix(taken.select("vec").limit(SAMPLE).toArrow().column(0))
    index = fit(sample, int(min(MOST_LISTS, max(4, round(n**0.5)), len(sample))))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = matrix(batch.column(1))
            if not len(x):
                continue
            unit = units(x)
            home = index.lists(unit)
            codes = index.codes(unit, home)
            err = np.linalg.norm(unit - index.centres[home] - index.decoded(codes), axis=1)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(home.astype(np.int32)), pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(err)], ["id", "vec", "list", "codes", "err"])

    placed = settle(good.mapInArrow(place, "id long, vec array<double>, list int, codes binary, err double"), "ann-index")
    measure(index, placed, is_query, k)
    # at most MOST_LISTS counts
    sizes = np.zeros(len(index.centres), np.int64)
    for r in placed.groupBy("list").count().collect():
        sizes[r["list"]] = r["count"]

    def probe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = matrix(batch.column(1))
            if not len(x):
                continue
            order = index.order(units(x))
            enough = (np.cumsum(sizes[order], axis=1) <= k).sum(1) + 1
            lists = [o[: max(index.probes, e)].astype(np.int32) for o, e in zip(order, enough, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([o[sizes[o] > 0] for o in lists], pa.list_(pa.int32()))], ["id", "vec", "lists"])

    asked = placed.where(is_query).select("id", "vec").mapInArrow(probe, "id long, vec array<double>, lists array<int>")
    visits = asked.select("id", "vec", F.explode("lists").alias("list"))
    # a row for each list, so at most MOST_LISTS: small whatever the data
    loads = spark.createDataFrame([(i, int(s)) for i, s in enumerate(sizes)], "list int, n long").select("list", F.ceil(F.col("n") / TILE_ROWS).cast("int").alias("tiles"))
    crowds = asked.select(F.explode("lists").alias("list")).groupBy("list").agg(F.ceil(F.count("*") / TILE_QUERIES).cast("int").alias("q_tiles"))
    shape = F.broadcast(loads.join(crowds, "list"))
    every = lambda c: F.explode(F.sequence(F.lit(0), F.col(c) - 1))
    mine = lambda c: F.pmod(F.xxhash64("id"), F.col(c)).cast("int")
    left = visits.join(shape, "list").select("list", every("tiles").alias("tile"), mine("q_tiles").alias("q_tile"), "id", "vec")
    right = placed.join(shape, "list").select("list", mine("tiles").alias("tile"), every("q_tiles").alias("q_tile"), "id", "vec", "codes", "err")
    keys = ["list", "tile", "q_tile"]

    def run(key: tuple[pa.Scalar, ...], queries: pa.Table, candidates: pa.Table) -> pa.Table:
        out = []
        if len(queries) and len(candidates):
            q_ids, q = queries.column("id").to_numpy(), matrix(queries.column("vec"))
            ids, x = candidates.column("id").to_numpy(), matrix(candidates.column("vec"))
            codes = np.frombuffer(b"".join(candidates.column("codes").to_pylist()), np.uint8).reshape(len(ids), -1)
            keep = once(q_ids, q)
            q_ids, q = q_ids[keep], scaled(q[keep])
            keep = once(ids, x)
            by_id = keep[np.argsort(ids[keep], kind="stable")]
            ids, x, codes = ids[by_id], scaled(x[by_id]), codes[by_id]
            slack = index.reach * candidates.column("err").to_numpy()[by_id] + 1e-9
            centre = index.centres[key[0].as_py()]
            for i in range(len(q_ids)):
                unit = q[i] / np.linalg.norm(q[i])
                looks = np.full(len(ids), centre @ unit)
                for m, (b, c) in enumerate(zip(index.books, index.cuts, strict=True)):
                    looks += (b @ unit[c])[codes[:, m]]
                looks[ids == q_ids[i]] = -np.inf
                near = best(ids, looks, rerank)
                near = near[ids[near] != q_ids[i]]
                scores = exact_cosines(q[i], x[near])
                if len(scores) >= k:
                    may = looks + slack >= np.partition(scores, len(scores) - k)[len(scores) - k]
                    may[near] = False
                    more = np.flatnonzero(may)
                    near, scores = np.concatenate([near, more]), np.concatenate([scores, exact_cosines(q[i], x[more])])
                top = best(ids[near], scores, k)
                out.append((np.full(len(top), q_ids[i]), ids[near[top]], scores[top]))
        cols = [np.concatenate(c) for c in zip(*out, strict=True)] if out else [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
        return pa.table({"query_id": cols[0], "id": cols[1], "score": cols[2]})

    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(run, "query_id long, id long, score double")
