"""Exact top-k inner products by bounds from segment means and deviations, coarse to fine.

On a segment of L components, a.b is at most L * mean(a) * mean(b) + |a - mean(a)| * |b - mean(b)|; summed over segments
this bounds the whole product from above (the squared distance from below), the more closely the finer the segments.
Queries and candidates meet in tiles of bounded size. In a tile, ``GROUP`` queries that lie close go through it together: the
coarsest level bounds all candidates, and the exact scores of those that look best give each query a first k-th score, which
every level raises. Only candidates that some query of the group may still need go on to the next level; those left after
the finest get exact scores, one by one where few pairs are left. Tiles return k rows a query, and the last step
keeps the k best of all tiles.

Edge cases: vectors that are null, empty, or hold null or non-finite components take no part; vectors are compared with
vectors of their own length only; a query is never its own candidate (by id); rows repeating an id and a vector count
once; ties go to the smaller id; an empty table gives no rows; other columns are not read, whatever their names. Scores are
exact integers; one beyond the range of a long is cut to it.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .vectors import best, matrix, once, usable

#: Largest tile: candidates and queries.
TILE_ROWS, TILE_QUERIES = 16_384, 4_096
#: Tiles that even small tables are cut into, for the sake of parallel work.
LEAST_TILES = 32
SEGMENTS = (1, 4, 16, 32)
#: Queries that go through a tile together, and candidates that give each its first bar.
GROUP, SEEDS = 32, 32
#: Candidates that the queries are put in order by.
PIVOTS = 64


def features(x: np.ndarray, segments: int) -> np.ndarray:
    """Columns whose inner products are the upper bounds at this resolution."""
    cuts = np.array_split(np.arange(x.shape[1]), min(segments, x.shape[1]))
    means = np.stack([x[:, c].mean(1) for c in cuts], 1)
    rest = np.stack([np.sqrt(((x[:, c] - x[:, c].mean(1, keepdims=True)) ** 2).sum(1)) for c in cuts], 1)
    return np.hstack([means * np.sqrt([len(c) for c in cuts]), rest])


def _products(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Exact inner products of all rows of q and x: in floats while they hold them, in longs, or in Python's numbers cut to longs."""
    most = float(np.abs(q).max(initial=0)) * float(np.abs(x).max(initial=0)) * max(1, x.shape[1])
    if most < 2**53:
        return np.rint(q @ x.T).astype(np.int64)
    if most < 2**62:
        return q.astype(np.int64) @ x.astype(np.int64).T
    whole = [[sum(int(a) * int(b) for a, b in zip(r, c, strict=True)) for c in x] for r in q]
    return np.array([[max(-(1 << 63), min((1 << 63) - 1, v)) for v in r] for r in whole], np.int64).reshape(len(q), len(x))


def tile_top(q_ids: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[float]]:
    """(place of the query, id, score) of the k best in one tile, and the share of all pairs that each level looked at, the exact
    scores last."""
    sizes = [s for s in SEGMENTS if s == 1 or s < x.shape[1]]
    q_levels, levels = [features(q, s) for s in sizes], [features(x, s) for s in sizes]
    q_norm, norm = np.linalg.norm(q, axis=1), np.linalg.norm(x, axis=1)
    looked, out = np.zeros(len(sizes) + 1), []
    # queries that lie next to the same of some candidates meet in a group, so that they need like candidates
    order = np.argsort((q @ x[:: -(-len(x) // PIVOTS)].T).argmax(1), kind="stable")
    for begin in range(0, len(order), GROUP):
        rows = order[begin : begin + GROUP]
        cols = np.arange(len(ids))
        alive = q_ids[rows, None] != ids[None, :]
        bar = np.full(len(rows), -np.inf)
        slack = 1e-9 * q_norm[rows] * norm.max(initial=0) + 1e-6
        for n, (mine, theirs) in enumerate(zip(q_levels, levels, strict=True)):
            bounds = np.where(alive, mine[rows] @ theirs[cols].T, -np.inf)
            looked[n] += bounds.size
            # the candidates that look best at this level raise the bar
            take = min(max(SEEDS, 4 * k), len(cols))
            first = np.argpartition(-bounds, take - 1, axis=1)[:, :take]
            if take >= k:
                seeds = np.einsum("qd,qsd->qs", q[rows], x[cols[first]])
                seeds = np.where(np.take_along_axis(alive, first, 1), seeds, -np.inf)
                # scores beyond a long are equal, so no bar is higher than the highest of them
                bar = np.maximum(bar, np.minimum(-np.partition(-seeds, k - 1, axis=1)[:, k - 1], 2.0**63) - slack)
            alive &= bounds + slack[:, None] >= bar[:, None]
            needed = alive.any(0)
            cols, alive = cols[needed], alive[:, needed]
            if not len(cols):
                break
        if alive.size and alive.mean() > 0.05:
            scores = _products(q[rows], x[cols])
            looked[-1] += alive.size
            lists = [(np.flatnonzero(a), s[a]) for a, s in zip(alive, scores, strict=True)]
        else:
            lists = [(at, _products(q[r : r + 1], x[cols[at]])[0]) for r, at in zip(rows, map(np.flatnonzero, alive), strict=True)]
            looked[-1] += alive.sum()
        for r, (at, scores) in zip(rows, lists, strict=True):
            top = best(ids[cols[at]], scores, k)
            out.append((np.full(len(top), r), ids[cols[at[top]]], scores[top]))
    return (*(np.concatenate(c) for c in zip(*out, strict=True)), (looked / max(1, len(q) * len(ids))).tolist())


def top_products(rows: DataFrame, is_query: Column, k: int = 10, scale: int = 1024, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """query_id, rank (from 1), the candidate's id under id_col's name, score: the k highest inner products of
    floor(scale * component) for each row where is_query, a condition on column ``id``, holds."""
    good = usable(rows, id_col, vec_col)
    whole = good.select("id", F.transform("vec", lambda v: F.floor(F.lit(float(scale)) * v).cast("double")).alias("vec"), F.size("vec").alias("dim"))
    n, n_q = (v or 0 for v in good.agg(F.count("*"), F.sum(is_query.cast("long"))).first())
    tiles = max(-(-n // TILE_ROWS), min(LEAST_TILES, -(-n // 64)), 1)
    q_tiles = max(1, -(-n_q // TILE_QUERIES))
    every = lambda count: F.explode(F.sequence(F.lit(0), F.lit(count - 1)))
    left = whole.where(is_query).select("dim", every(tiles).alias("tile"), F.pmod(F.xxhash64("id"), F.lit(q_tiles)).cast("int").alias("q_tile"), "id", "vec")
    right = whole.select("dim", F.pmod(F.xxhash64("id"), F.lit(tiles)).cast("int").alias("tile"), every(q_tiles).alias("q_tile"), "id", "vec")
    keys = ["dim", "tile", "q_tile"]

    def run(queries: pa.Table, candidates: pa.Table) -> pa.Table:
        sides = []
        for t in (queries, candidates):
            ids, vec = t.column("id").to_numpy(), matrix(t.column("vec"))
            keep = once(ids, vec)
            ids, vec = ids[keep], vec[keep]
            sides.append((ids, vec))
        (q_ids, q), (ids, x) = sides
        if not len(q_ids) or not len(ids):
            return pa.table({c: pa.array([], pa.int64()) for c in ("query_id", "id", "score")})
        i, found, scores, _ = tile_top(q_ids, q, ids, x, k)
        return pa.table({"query_id": q_ids[i], "id": found, "score": scores})

    tops = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(run, "query_id long, id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "id")
    return tops.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), F.col("id").alias(id_col), "score")
