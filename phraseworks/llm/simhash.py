"""SimHash near-duplicates through a segment-popcount grid.

A fingerprint's bits fall into segments of two; the counts of set bits, one a segment, are a point whose Manhattan
distance to another point never exceeds the fingerprints' Hamming distance. The segments form groups; two fingerprints
within the limit agree in at least one group to within ``limit // groups``, at most 2, which the range join finds: every
point goes to its own cell and to the cells one step away, so two points at most two steps apart meet in a cell. In a
cell the Manhattan bound over all segments comes first, then the exact Hamming distance. A cell gives back only a
spanning forest of its links, so a dense group costs as many rows as it has members. Cells over ``TILE`` points are cut
into blocks, and each pair of blocks is a task of its own.

SimHash distances of texts as alike as 0.8 spread up to some 14 of 64 bits, where unrelated texts begin to meet and the grid
is no filter any more. So with ``similar`` the grid, at its small limit, proposes one part of the pairs, and a banded
signature of minimum hashes the other: texts that agree in all ``ROWS`` places of one of ``BANDS`` bands meet in a cell, where
the first ``PLACES`` bytes of the signature take out pairs that are far below the share. Two sets 0.8 alike share no band
with a probability of 0.003. What both leave only proposes groups: the shingle sets (64-bit hashes, common ones over all) of a
group's texts then meet once, and every link of the result was compared on them and is at least ``similar``.

Edge cases: null and empty texts have fingerprint zero and link like any other; texts of fewer words than a shingle are
one shingle; very long texts are hashed whole; rows with equal fingerprints (with ``similar``: equal sets) always share a
component; an empty table gives no rows; other columns are not read. A component is of texts, not of ids: unlike texts under
one repeated id stay apart, though they may show the same component_id. Null ids never name a component unless it has no other.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows, settle
from .components import components

#: Points of a cell that one task compares with each other.
TILE = 2048
SEED = 42
#: Points with their shingle sets that one task compares with each other.
SET_TILE = 512
#: Bits at which the grid proposes pairs that are then compared on their shingles.
PROPOSED = 4
#: Minimum hashes: bands of rows, of which the first PLACES also give a byte each to the signature; the odd factors of the hashes.
BANDS, ROWS, PLACES = 20, 6, 32
_ODD = np.array([int.from_bytes(xxhash.xxh64_digest(bytes([i])), "big") | 1 for i in range(BANDS * ROWS)], np.uint64)
_FOLD = np.array([int.from_bytes(xxhash.xxh64_digest(bytes([i, 1])), "big") | 1 for i in range(ROWS)], np.uint64)
_PAIRS = np.uint64(0x5555555555555555)


def hashes(text: str | None, shingle: int) -> list[int]:
    words = (text or "").encode().lower().split()  # bytes: only A-Z change, and words end at blanks and 0x09-0x0D
    of, join = xxhash.xxh64_intdigest, b" ".join
    if not words:
        return []
    if len(words) <= shingle:
        return [of(join(words), SEED)]
    return [of(join(w), SEED) for w in zip(*(words[i:] for i in range(shingle)), strict=False)]


def fingerprint(found: list[int]) -> int:
    """Bits that are set in over half of the hashes; 0 without any."""
    sums, step = np.zeros(64, np.int64), 1 << 16
    for i in range(0, len(found), step):
        bits = np.unpackbits(np.array(found[i : i + step], dtype=">u8").view(np.uint8).reshape(-1, 8), axis=1)
        sums += bits.sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * sums > len(found)).tobytes(), "big")


def least_hashes(found: list[int]) -> np.ndarray:
    """The minimum of each hash function over the shingles."""
    h, lows = np.array(found, np.uint64), np.full(len(_ODD), np.iinfo(np.uint64).max, np.uint64)
    h ^= h >> np.uint64(31)
    for i in range(0, len(h), 2048):
        lows = np.minimum(lows, (_ODD[:, None] * h[i : i + 2048]).min(1))
    return lows


def signature(lows: np.ndarray) -> bytes:
    """A byte of each of the first PLACES minimum hashes."""
    return ((lows[:PLACES] * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(56)).astype(np.uint8).tobytes()


def bands(lows: np.ndarray) -> bytes:
    """A key of 64 bits for each band."""
    keys = (lows.reshape(BANDS, ROWS) * _FOLD).sum(1, dtype=np.uint64)
    return (keys ^ (keys >> np.uint64(29))).tobytes()


def shingles(found: list[int]) -> bytes:
    """The distinct hashes in rising order, eight bytes each."""
    return np.unique(np.array(found, np.uint64)).tobytes()


def similarity(a: np.ndarray, b: np.ndarray) -> float:
    """Common elements over all of two sorted sets of distinct hashes; 1 for two empty ones."""
    if not len(a) or not len(b):
        return float(len(a) == len(b))
    few, many = (a, b) if len(a) < len(b) else (b, a)
    common = int((many[np.minimum(np.searchsorted(many, few), len(many) - 1)] == few).sum())
    return common / (len(a) + len(b) - common)


def fingerprints(docs: DataFrame, shingle: int, id_col: str = "doc_id", text_col: str = "text", signed: bool = False) -> DataFrame:
    """id, print (the 64 bits as a signed long)[, body (64-bit hash of the text), digest (128 bits of the set of shingles), sign, bands]."""

    def make():
        def work(keys, texts, *bodies):
            found = [hashes(t, shingle) for t in texts]
            prints = np.array([fingerprint(h) for h in found], dtype=np.uint64).view(np.int64)
            if not signed:
                return {id_col: keys, "print": prints}
            lows = [least_hashes(h) for h in found]
            return {id_col: keys, "print": prints, "body": bodies[0], "digest": [xxhash.xxh128_digest(shingles(h)) for h in found], "sign": [signature(x) for x in lows], "bands": [bands(x) if h else b"" for x, h in zip(lows, found, strict=True)]}

        return work

    text = F.col(text_col).cast("string")
    rows = docs.select(F.col(id_col).cast("long").alias(id_col), text.alias("text"), *([F.xxhash64(text).alias("body")] if signed else []))
    return map_rows(rows, make, f"{id_col} long, print long" + ", body long, digest binary, sign binary, bands binary" * signed)


def counts_of(prints: np.ndarray) -> np.ndarray:
    """Set bits of each two-bit segment, again as two bits."""
    return (prints & _PAIRS) + ((prints >> np.uint64(1)) & _PAIRS)


def group_masks(limit: int) -> list[int]:
    """Bit masks of the segment groups: as few groups as let each be searched within two steps."""
    groups = limit // 3 + 1
    cuts = [round(i * 32 / groups) for i in range(groups + 1)]
    return [sum(3 << (2 * s) for s in range(a, b)) for a, b in zip(cuts, cuts[1:], strict=False)]


def cells_of(prints: np.ndarray, limit: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Cells that each print goes to: (index of the print, group, cell)."""
    counts, out = counts_of(prints), []
    rows = np.arange(len(prints))
    for g, mask in enumerate(group_masks(limit)):
        own = counts & np.uint64(mask)
        near = [(rows, own)]
        if limit // len(group_masks(limit)):
            for s in range(32):
                if mask >> (2 * s) & 3:
                    here, one = (own >> np.uint64(2 * s)) & np.uint64(3), np.uint64(1 << (2 * s))
                    near += [(rows[here < 2], own[here < 2] + one), (rows[here > 0], own[here > 0] - one)]
        index, cell = (np.concatenate(x) for x in zip(*near, strict=True))
        out.append((index, np.full(len(index), g, np.int32), cell))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def bound(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Manhattan distance of two points given as packed counts."""
    high = np.uint64(0xAAAAAAAAAAAAAAAA)
    # per segment |x - y| of numbers 0..2: the exclusive or is right except for 1 against 2, which it gives as 3
    x = a ^ b
    three = x & (x >> np.uint64(1)) & _PAIRS
    x = (x & ~(three * np.uint64(3))) | three
    return np.bitwise_count(x & _PAIRS).astype(np.int16) + 2 * np.bitwise_count(x & high).astype(np.int16)


def forest(both: np.ndarray, cut: int | None, limit: int, signs: np.ndarray | None = None, agree: int = 0, sets: list[np.ndarray] | None = None, similar: float = 0.0) -> list[tuple[int, int]]:
    """Spanning forest of the links within ``limit`` among the prints, or between those before and behind ``cut``, as places. With
    signs (a row of bytes each) at least ``agree`` places must be equal too, and with sets their similarity must reach ``similar``."""
    points, parent = counts_of(both), list(range(len(both)))
    label = np.arange(len(both))

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    out, rows = [], len(both) if cut is None else cut
    for first in range(0, rows, 32):
        block = np.arange(first, min(first + 32, rows))
        start = first + 1 if cut is None else cut
        apart = label[block, None] != label[None, start:]  # what is connected needs no further link
        i, j = np.nonzero(apart & (bound(points[None, start:], points[block, None]) <= limit) if limit < 64 else apart)
        i, j = block[i], j + start
        if cut is None:
            i, j = i[j > i], j[j > i]
        if limit < 64:
            keep = np.bitwise_count(both[i] ^ both[j]) <= limit
            i, j = i[keep], j[keep]
        if signs is not None and len(i):
            keep = (signs[i] == signs[j]).sum(1) >= agree
            i, j = i[keep], j[keep]
        before = len(out)
        for x, y in zip(i.tolist(), j.tolist(), strict=True):
            a, b = root(x), root(y)
            if a != b and (sets is None or similarity(sets[x], sets[y]) >= similar):
                parent[b] = a
                out.append((x, y))
        if len(out) > before:
            label = np.array(parent)
            while not np.array_equal(label, up := label[label]):
                label = up
    return out


def _cell_rows(prints: DataFrame, limit: int) -> DataFrame:
    """grp, cell for each cell a print goes to, with all columns of prints."""
    at = prints.columns.index("print")
    names = prints.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 4096):
                part = batch.slice(start, 4096)
                index, group, cell = cells_of(part.column(at).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64), limit)
                # the group's own bits never reach above its mask, so number and cell make one exact key with the group
                yield pa.RecordBatch.from_arrays([pa.array(group), pa.array(cell.view(np.int64)), *(c.take(pa.array(index)) for c in part.columns)], ["grp", "cell", *names])

    return prints.mapInArrow(run, "grp int, cell long, " + ", ".join(f"{n} {t}" for n, t in prints.dtypes).replace("bigint", "long"))


def links(prints: DataFrame, limit: int) -> DataFrame:
    """Links (u, v) that span the same components as all pairs of distinct prints within ``limit`` bits."""
    return _compared(settle(_cell_rows(prints.select("print").distinct(), limit), "simhash-cells"), limit, TILE)


def banded_links(texts: DataFrame, similar: float) -> DataFrame:
    """Links (u, v) between nodes of texts (node, print, sign, bands) that share a band and nearly a share ``similar`` of equal places:
    they span the same components as all such pairs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for start in range(0, whole.num_rows, 4096):
                part = whole.slice(start, 4096)
                keys = [np.frombuffer(x, np.int64) for x in part.column(3).to_pylist()]
                at = np.repeat(np.arange(len(keys)), [len(k) for k in keys])
                group = np.concatenate([np.arange(len(k), dtype=np.int32) for k in keys]) if keys else np.zeros(0, np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(group), pa.array(np.concatenate(keys) if keys else np.zeros(0, np.int64)), *(part.column(i).take(pa.array(at)) for i in (1, 0, 2))], ["grp", "cell", "print", "node", "sign"])

    rows = texts.select("node", "print", "sign", "bands").mapInArrow(run, "grp int, cell long, print long, node long, sign binary")
    return _compared(settle(rows, "simhash-bands"), 64, TILE, similar)


def verified_links(points: DataFrame, similar: float) -> DataFrame:
    """Links (u, v) that span the same components as all pairs of a proposed group with nearly a share ``similar`` of equal places and
    with shingle sets at least ``similar`` alike. points: root (of the proposed group), print, node, sign, shingles."""
    return _compared(points.select(F.lit(0).alias("grp"), F.col("root").alias("cell"), "print", "node", "sign", "shingles"), 64, SET_TILE, similar)


def _compared(rows: DataFrame, limit: int, tile: int, similar: float | None = None) -> DataFrame:
    """Spanning links of the points in each cell: rows (grp, cell, print[, node, sign[, shingles]])."""
    extra = [c for c in ("node", "sign", "shingles") if c in rows.columns]
    signed, exact = "sign" in extra, "shingles" in extra
    # three standard deviations under the share, as a signature only estimates it
    agree = int(np.ceil(PLACES * similar - 3 * np.sqrt(PLACES * similar * (1 - similar)))) if signed else 0
    # cells of one tile, nearly all, go as they are: only crowded ones are looked up and dealt to pairs of blocks
    crowds = rows.groupBy("grp", "cell").agg(F.count("*").alias("n")).where(F.col("n") > tile).select(F.col("grp").alias("g"), F.col("cell").alias("c"), F.ceil(F.col("n") / tile).cast("int").alias("blocks"))
    dealt = rows.join(crowds, (F.col("grp") == F.col("g")) & (F.col("cell") == F.col("c")), "left").withColumn("block", F.coalesce(F.pmod(F.xxhash64("print", *extra[:1]), F.col("blocks")), F.lit(0)).cast("int"))
    pairs = F.when(F.col("blocks") > 1, F.sequence(F.lit(0), F.col("blocks") - 1)).otherwise(F.array(F.lit(0)))
    tiled = dealt.select("grp", "cell", "print", *extra, "block", F.explode(pairs).alias("other")).select(
        "grp", "cell", F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "block", "print", *extra)
    keys = ["grp", "cell", "low", "high"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Tiles come one after another; the last of a batch waits for the next one."""
        held: list[pa.RecordBatch] = []

        def work(table: pa.Table) -> pa.RecordBatch:
            cols = [table.column(i).to_numpy() for i in range(6)]
            prints, names = cols[5].view(np.uint64), table.column(6).to_numpy() if signed else cols[5]
            signs = np.frombuffer(b"".join(table.column(7).to_pylist()), np.uint8).reshape(-1, PLACES) if signed else None
            sets = [np.frombuffer(x, np.uint64) for x in table.column(8).to_pylist()] if exact else None
            edges: list[np.ndarray] = []
            cuts = np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols[:4]], axis=0)) + 1
            for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(cols[0])], strict=True):
                if b - a < 2:
                    continue
                place, cut = np.arange(a, b), None
                if cols[2][a] != cols[3][a]:
                    low = cols[4][a:b] == cols[2][a]
                    place, cut = np.concatenate([place[low], place[~low]]), int(low.sum())
                found = forest(prints[place], cut, limit, signs[place] if signed else None, agree, [sets[i] for i in place] if exact else None, similar or 0.0)
                if found:
                    edges.append(names[place[np.array(found)]])
            e = np.concatenate(edges) if edges else np.zeros((0, 2), np.int64)
            return pa.RecordBatch.from_pydict({"u": e[:, 0], "v": e[:, 1]})

        for batch in batches:
            if not batch.num_rows:
                continue
            if held:
                last, cols = held[-1], [batch.column(i).to_numpy() for i in range(4)]
                same = np.all([c == last.column(i)[last.num_rows - 1].as_py() for i, c in enumerate(cols)], axis=0)
                end = len(same) if same.all() else int(np.argmin(same))
                held.append(batch.slice(0, end))
                if end == batch.num_rows:
                    continue
                yield work(pa.Table.from_batches(held))
                batch = batch.slice(end)
            cols = [batch.column(i).to_numpy() for i in range(4)]
            other = np.flatnonzero(np.any([c != c[-1] for c in cols], axis=0))
            cut = int(other[-1]) + 1 if len(other) else 0
            if cut:
                yield work(pa.Table.from_batches([batch.slice(0, cut)]))
            held = [batch.slice(cut)]
        if held:
            yield work(pa.Table.from_batches(held))

    return tiled.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(run, "u long, v long").distinct()


def near_duplicates(docs: DataFrame, shingle: int = 5, limit: int = 4, similar: float | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row a document: id, fingerprint (16 lowercase hex digits), component_id (least id of the component). Documents link when
    their prints differ in at most ``limit`` bits; with ``similar``, when their sets of shingles are at least that much alike."""
    if similar is not None:
        rows, named = _similar_groups(docs, shingle, similar, id_col, text_col)
        names = settle(named.groupBy("root").agg(F.min("low").alias("component_id")), "simhash-names")
        ids = settle(named.join(names, "root").select(F.col("digest").alias("key"), "component_id"), "simhash-ids")
        found = rows.join(ids, F.col("digest") == F.col("key"), "left")
    else:
        rows = settle(fingerprints(docs, shingle, id_col, text_col), "fingerprints")
        least = rows.groupBy("print").agg(F.min(id_col).alias("low"))
        nodes = components(links(rows, limit), "simhash-components")
        # written before they meet the rows again, so that a join can split a group that holds many of them
        named = settle(least.join(nodes, F.col("print") == F.col("node"), "left").select("print", "low", F.coalesce("component", "print").alias("root")), "simhash-named")
        names = settle(named.groupBy("root").agg(F.min("low").alias("component_id")), "simhash-names")
        ids = settle(named.join(names, "root").select(F.col("print").alias("key"), "component_id"), "simhash-ids")
        found = rows.join(ids, F.col("print") == F.col("key"), "left")
    return found.select(id_col, F.lower(F.lpad(F.hex("print"), 16, "0")).alias("fingerprint"), "component_id")


def one_of_each(docs: DataFrame, shingle: int = 5, similar: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with one row of each component by ``similar``: the one of the least id (null ids come last, equal ids by a hash of the
    text); of rows with the same id and text any one. All columns stay as they are."""
    rows, named = _similar_groups(docs, shingle, similar, id_col, text_col)
    order = F.struct(F.col(id_col).isNull().alias("last"), F.col(id_col).alias("of_id"), F.col("body").alias("of_body"))
    per_text = rows.groupBy("digest").agg(F.min(order).alias("first"))
    firsts = per_text.join(named.select(F.col("digest").alias("key"), "root"), F.col("digest") == F.col("key")).groupBy("root").agg(F.min("first").alias("first")).select("first.of_id", "first.of_body")
    copies = rows.groupBy(F.col(id_col).alias("row_id"), F.col("body").alias("row_body")).agg(F.count("*").alias("copies"))
    stay = settle(firsts.join(copies, F.col("of_id").eqNullSafe(F.col("row_id")) & (F.col("of_body") == F.col("row_body"))).select("of_id", "of_body", "copies"), "simhash-stay")
    # the rows travel as one struct, so that no column of theirs meets a name used here
    held = docs.select(F.struct(*docs.columns).alias("row"), F.col(id_col).cast("long").alias("held_id"), F.xxhash64(F.col(text_col).cast("string")).alias("held_body"))
    kept = held.join(stay, F.col("held_id").eqNullSafe(F.col("of_id")) & (F.col("held_body") == F.col("of_body"))).select("row", "held_id", "held_body", "copies")
    once = kept.where("copies = 1").select("row").unionByName(kept.where("copies > 1").dropDuplicates(["held_id", "held_body"]).select("row"))
    return once.select(*[F.col("row").getField(c).alias(c) for c in docs.columns])


def _similar_groups(docs: DataFrame, shingle: int, similar: float, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame]:
    """The documents' fingerprint rows, and of each distinct set of shingles: digest, low (its least id), root (a number that the
    sets of one component share)."""
    rows = settle(fingerprints(docs, shingle, id_col, text_col, signed=True), "fingerprints")
    order = F.struct(F.col(id_col).isNull().alias("last"), F.col(id_col).alias("of_id"), F.col("body").alias("of_body"))
    # a node is a distinct set of shingles, numbered where it is written
    texts = settle(rows.groupBy("digest").agg(F.min(order).alias("first"), F.min("print").alias("print"), F.min("sign").alias("sign"), F.min("bands").alias("bands")).select(F.monotonically_increasing_id().alias("node"), "digest", "first.of_id", "first.of_body", "print", "sign", "bands"), "simhash-texts")
    prints = texts.groupBy("print").agg(F.min("node").alias("home"))
    near = links(texts, PROPOSED)
    home = lambda c: prints.select(F.col("print").alias(f"{c}_print"), F.col("home").alias(f"{c}_home"))
    by_grid = near.join(home("u"), F.col("u") == F.col("u_print")).join(home("v"), F.col("v") == F.col("v_print")).select(F.col("u_home").alias("u"), F.col("v_home").alias("v"))
    same_print = texts.join(prints.withColumnRenamed("print", "p"), F.col("print") == F.col("p")).where("node <> home").select(F.col("node").alias("u"), F.col("home").alias("v"))
    found = components(by_grid.union(same_print).union(banded_links(texts, similar)), "simhash-groups")
    # a group's least node has no row of its own
    groups = found.union(found.select("component", "component").distinct()).toDF("member", "root")
    members = texts.join(groups, F.col("node") == F.col("member")).select("node", "digest", "of_id", "of_body", "print", "sign", "root")
    points = settle(_with_shingles(docs, members, shingle, id_col, text_col), "simhash-shingles")
    nodes = components(verified_links(points, similar), "simhash-components")
    named = texts.join(nodes.withColumnRenamed("node", "n"), F.col("node") == F.col("n"), "left").select("digest", F.col("of_id").alias("low"), F.coalesce("component", "node").alias("root"))
    return rows, settle(named, "simhash-named")


def _with_shingles(docs: DataFrame, members: DataFrame, shingle: int, id_col: str, text_col: str) -> DataFrame:
    """root, print, node, sign, shingles of the members, from the text of one document each; rows that repeat an id and a text meet
    in the aggregation before they are read."""
    text = F.col(text_col).cast("string")
    texts = docs.select(F.col(id_col).cast("long").alias("held_id"), F.xxhash64(text).alias("held_body"), text.alias("held_text"))
    joined = texts.join(members, F.col("held_id").eqNullSafe(F.col("of_id")) & (F.col("held_body") == F.col("of_body")))
    rows = joined.groupBy("node").agg(F.min("held_text").alias("held_text"), F.min("print").alias("print"), F.min("sign").alias("sign"), F.min("root").alias("root"))

    def make():
        def work(nodes, bodies, prints, signs, roots):
            return {"root": roots, "print": prints, "node": nodes, "sign": signs, "shingles": [shingles(hashes(b, shingle)) for b in bodies]}

        return work

    return map_rows(rows, make, "root long, print long, node long, sign binary, shingles binary")
