"""Language-model scores by deleted interpolation.

Maximum-likelihood estimates of all orders are mixed from the highest down, with one weight for each order and each
class of context frequency (powers of two). The weights come from expectation-maximisation over training documents whose
own counts are deleted, so each is held out from the counts that predict it.

Counts travel by request and reply. Documents form blocks of bounded size; a block asks once for each distinct n-gram it
has (sorted 64-bit hashes, differences packed), whatever its frequency, so no word is hot. Buckets of the hash space add
up the blocks' training counts and answer in the order asked. The replies grow with the corpus and nothing of that kind
passes through the driver: it gets the totals N and V and the histogram for the weights, whose cells are bounded by the grid
(class and quarter octave of each order above the base). An n-gram is its 64-bit hash: two that collide count as one.

Edge cases: null text is empty and has only its end token; very long texts are scored whole; repeated rows count and are
scored each; a null id falls into fold 0 and is in training; an empty table gives no rows; other columns are not read, whatever
their names; where nothing is in training all counts are 0 and the score is the base score.
"""

from __future__ import annotations

from collections import defaultdict
from itertools import count

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settle

#: Text of a block and of a bucket; hashes of a bucket that are added up at a time.
BLOCK_BYTES, BUCKET_BYTES, LEAST, RUN = 4 << 20, 32 << 20, 64, 1 << 18
CLASSES = 24
_MIX = np.uint64(0x9E3779B97F4A7C15)


def _packed(values: np.ndarray) -> bytes:
    """Unsigned longs as compressed byte planes; small numbers cost next to nothing."""
    planes = np.ascontiguousarray(values.astype("<u8").view(np.uint8).reshape(-1, 8).T).tobytes()
    return len(planes).to_bytes(8, "little") + pa.compress(planes, "zstd", asbytes=True)


def _unpacked(data: bytes) -> np.ndarray:
    size = int.from_bytes(data[:8], "little")
    planes = np.frombuffer(pa.decompress(data[8:], decompressed_size=size, codec="zstd", asbytes=True) if size else b"", np.uint8)
    return np.ascontiguousarray(planes.reshape(8, -1).T).view("<u8").ravel().astype(np.uint64)


def _mixed(x: np.ndarray) -> np.ndarray:
    x = x * _MIX
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


class Block:
    """Tokens of some documents, with the hash of the n-gram that ends at each token."""

    def __init__(self, texts: pa.ChunkedArray, order: int) -> None:
        known: dict[bytes, int] = defaultdict(count().__next__)
        ids, lengths = [], []
        for text in texts:
            words = (text.as_py() or "").encode().lower().split()
            words.append(b"")  # no word is empty, so this is the end token, and as a context the start
            ids.append(np.fromiter(map(known.__getitem__, words), np.int32, len(words)))
            lengths.append(len(words))
        self.lengths = np.array(lengths, np.int64)
        self.starts = np.concatenate([[0], np.cumsum(self.lengths)[:-1]]).astype(np.int64)
        own = np.array([xxhash.xxh64_intdigest(w) for w in known], np.uint64)
        self.keys, self.back = [], []
        tokens = np.concatenate(ids) if ids else np.zeros(0, np.int32)
        grams, words = own[tokens], own[tokens]
        doc = np.repeat(np.arange(len(self.lengths), dtype=np.int32), self.lengths)
        at = (np.arange(len(tokens)) - self.starts[doc]).astype(np.int32) if len(tokens) else np.zeros(0, np.int32)
        start = np.uint64(xxhash.xxh64_intdigest(b""))
        for k in range(order):
            if k:
                earlier = np.full(len(words), start, np.uint64)
                inside = at >= k
                earlier[inside] = words[np.flatnonzero(inside) - k]
                grams = _mixed(grams + _mixed(earlier + np.uint64(k)))
            # the words' hashes are sorted once a distinct word
            keys, back = np.unique(grams if k else own, return_inverse=True)
            back = back if k else back[tokens]
            self.keys.append(keys)
            self.back.append(back.astype(np.int32))
        self.doc, self.first = doc, at == 0

    def counts(self, train: np.ndarray) -> list[np.ndarray]:
        weight = train[self.doc].astype(np.float64)
        return [np.bincount(b, weights=weight, minlength=len(k)).astype(np.uint64) for k, b in zip(self.keys, self.back, strict=True)]


def _ends(keys: np.ndarray, buckets: int) -> np.ndarray:
    """Where each bucket, a range of the hash space, ends among sorted keys."""
    return np.searchsorted(((keys >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32), np.arange(buckets), side="right")


REQUEST = "level int, bucket int, block int, hashes binary, counts binary"
REPLY = "level int, bucket int, block int, totals binary, distinct long, tokens long"


def _request(order: int, buckets: int):
    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        block = Block(table.column("text"), order)
        rows = []
        for level, (keys, counts) in enumerate(zip(block.keys, block.counts(table.column("train").to_numpy()), strict=True)):
            begin = 0
            for bucket, end in enumerate(_ends(keys, buckets)):
                if end > begin:
                    part = keys[begin:end]
                    rows.append((level, bucket, key[0].as_py(), _packed(np.diff(part, prepend=np.uint64(0))), _packed(counts[begin:end])))
                begin = end
        return pa.table(dict(zip(("level", "bucket", "block", "hashes", "counts"), map(pa.array, zip(*rows, strict=True), (pa.int32(),) * 3 + (pa.binary(),) * 2), strict=True)))

    return run


def _reply(table: pa.Table) -> pa.Table:
    """Totals of a bucket in the order asked. The requests come sorted, so the bucket is worked through in runs of its hash range and
    only a run's keys and places are held beside the requests; totals take the place of the hashes they answer."""
    asked = [np.cumsum(_unpacked(x.as_py())) for x in table.column("hashes")]
    own = [_unpacked(x.as_py()).astype(np.uint32) for x in table.column("counts")]
    longest = max(asked, key=len)
    runs = -(-sum(map(len, asked)) // RUN)
    borders = longest[np.arange(1, runs) * len(longest) // runs]
    ends = [[0, *np.searchsorted(a, borders).tolist(), len(a)] for a in asked]
    distinct = tokens = 0
    for r in range(runs):
        spans = [slice(e[r], e[r + 1]) for e in ends]
        keys, back = np.unique(np.concatenate([a[x] for a, x in zip(asked, spans, strict=True)]), return_inverse=True)
        totals = np.bincount(back, weights=np.concatenate([c[x] for c, x in zip(own, spans, strict=True)]), minlength=len(keys)).astype(np.uint64)
        distinct, tokens, at = distinct + int((totals > 0).sum()), tokens + int(totals.sum()), 0
        for a, x in zip(asked, spans, strict=True):
            a[x] = totals[back[at : at + x.stop - x.start]]
            at += x.stop - x.start
    first = [1] + [0] * (len(asked) - 1)
    return pa.table({
        **{c: table.column(c) for c in ("level", "bucket", "block")},
        "totals": pa.array([_packed(a) for a in asked], pa.binary()),
        "distinct": pa.array([f * distinct for f in first], pa.int64()),
        "tokens": pa.array([f * tokens for f in first], pa.int64()),
    })


def _totals(replies: pa.Table, order: int) -> list[np.ndarray]:
    replies = replies.sort_by([("level", "ascending"), ("bucket", "ascending")])
    levels = replies.column("level").to_numpy()
    blobs = replies.column("totals")
    return [np.concatenate([np.zeros(0, np.uint64), *(_unpacked(blobs[int(i)].as_py()) for i in np.flatnonzero(levels == k))]) for k in range(order)]


class Estimates:
    """Per token: the base probability, and for every higher order its estimate's ratio to the base and its context's class."""

    def __init__(self, block: Block, totals: list[np.ndarray], n: int, v: int, deleted: bool) -> None:
        counts = [t[b].astype(np.float64) for t, b in zip(totals, block.back, strict=True)]
        start = totals[0][np.searchsorted(block.keys[0], np.uint64(xxhash.xxh64_intdigest(b"")))].astype(np.float64) if len(block.keys[0]) else 0.0
        starts = np.full(len(block.doc), start)
        if deleted:  # take the document's own n-grams out
            for k, b in enumerate(block.back):
                _, back, own = np.unique(block.doc.astype(np.int64) * (len(block.keys[k]) + 1) + b, return_inverse=True, return_counts=True)
                counts[k] = counts[k] - own[back]
            starts, n = starts - 1, n - block.lengths[block.doc]
        self.known = counts[0] > 0
        self.base = (counts[0] + 0.5) / (n + 0.5 * (v + 1))
        self.ratios, self.classes = [], []
        for k in range(1, len(counts)):
            context = np.where(block.first, starts, np.concatenate([[0.0], counts[k - 1][:-1]]))
            self.ratios.append(np.divide(counts[k], context, out=np.zeros_like(context), where=context > 0) / self.base)
            self.classes.append(np.where(context > 0, np.minimum(np.floor(np.log2(np.maximum(context, 1))) + 1, CLASSES - 1), 0).astype(np.int64))

    def mixed(self, weights: np.ndarray) -> np.ndarray:
        """The mixture's ratio to the base."""
        out = np.ones(len(self.base))
        for w, r, c in zip(weights, self.ratios, self.classes, strict=True):
            out = w[c] * r + (1 - w[c]) * out
        return out


def _histogram(order: int, n: int, v: int):
    """Tokens of deleted documents by context classes and by estimates on a grid of quarter octaves, with the exact sums."""
    names = [f"{x}{k}" for k in range(1, order) for x in ("c", "q")]

    def run(docs: pa.Table, replies: pa.Table) -> pa.Table:
        sums = [f"r{k}" for k in range(1, order)]
        if not len(docs):
            return pa.table({**{x: pa.array([], pa.int32()) for x in names}, "n": pa.array([], pa.int64()), **{x: pa.array([], pa.float64()) for x in sums}})
        block = Block(docs.column("text"), order)
        e = Estimates(block, _totals(replies, order), n, v, deleted=True)
        use = docs.column("train").to_numpy()[block.doc] == 1
        cols, low = [], []
        for r, c in zip(e.ratios, e.classes, strict=True):
            low += [0, -99]
            cols += [c[use], np.where(r[use] > 0, np.clip(np.floor(4 * np.log2(np.maximum(r[use], 1e-12))), -60, 160), -99).astype(np.int64)]
        # one column joins at a time: the cells so far, numbered, and the column make one number, as rows of columns are slow to sort
        grid, back = np.zeros((1, 0), np.int64), np.zeros(int(use.sum()), np.int64)
        for c, least in zip(cols, low, strict=True):
            cells, back = np.unique(back * 260 + (c - least), return_inverse=True)
            grid = np.column_stack([grid[cells // 260], cells % 260 + least])
        out = {x: pa.array(grid[:, i].astype(np.int32)) for i, x in enumerate(names)}
        out["n"] = pa.array(np.bincount(back, minlength=len(grid)).astype(np.int64))
        return pa.table(out | {x: pa.array(np.bincount(back, weights=r[use], minlength=len(grid)).astype(np.float64)) for x, r in zip(sums, e.ratios, strict=True)})

    return run, ", ".join([f"{x} int" for x in names] + ["n long"] + [f"r{k} double" for k in range(1, order)])


def learn_weights(counts: np.ndarray, ratios: list[np.ndarray], classes: list[np.ndarray], rounds: int = 60) -> np.ndarray:
    """Expectation-maximisation: a weight for each order above the base and each context class; class 0 (unseen) has none."""
    weights = np.full((len(ratios), CLASSES), 0.5)
    weights[:, 0] = 0
    for _ in range(rounds):
        below = [np.ones(len(counts))]
        for w, r, c in zip(weights, ratios, classes, strict=True):
            below.append(w[c] * r + (1 - w[c]) * below[-1])
        reach = counts.astype(float)
        for k in range(len(ratios) - 1, -1, -1):
            c = classes[k]
            own = reach * weights[k][c] * ratios[k] / np.maximum(below[k + 1], 1e-300)
            up, all_ = np.bincount(c, own, CLASSES), np.bincount(c, reach, CLASSES)
            weights[k] = np.where(all_ > 0, up / np.maximum(all_, 1e-300), weights[k])
            reach = reach - own
        weights[:, 0] = 0
        weights = np.clip(weights, 0, 0.999)
    return weights


def _scores(order: int, n: int, v: int, weights: np.ndarray):
    def run(docs: pa.Table, replies: pa.Table) -> pa.Table:
        if not len(docs):
            return pa.table({"id": pa.array([], pa.int64()), "held_out": pa.array([], pa.bool_()), "n_tokens": pa.array([], pa.int64()), "n_known": pa.array([], pa.int64()), "base_score": pa.array([], pa.float64()), "score": pa.array([], pa.float64())})
        block = Block(docs.column("text"), order)
        e = Estimates(block, _totals(replies, order), n, v, deleted=False)
        base = np.log10(e.base)
        add = lambda x: np.add.reduceat(x, block.starts)  # noqa: E731  every document has a token
        train = docs.column("train").to_numpy()
        return pa.table({"id": docs.column("id"), "held_out": pa.array(train == 0), "n_tokens": pa.array(block.lengths), "n_known": pa.array(add(e.known.astype(np.int64))), "base_score": pa.array(add(base)), "score": pa.array(add(base + np.log10(e.mixed(weights))))})

    return run


def score(docs: DataFrame, in_training: Column, order: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, held_out, n_tokens, n_known, train_tokens, base_score, score for every document. in_training is a condition on docs; every
    training document, its own counts deleted, teaches the mixture weights."""
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(in_training, F.lit(False)).cast("int").alias("train"), F.col(text_col).cast("string").alias("text"))
    n_docs, size = (x or 0 for x in rows.agg(F.count("*"), F.sum(F.octet_length("text"))).first())
    least = max(1, min(LEAST, -(-n_docs // 64)))
    blocks, buckets = max(-(-size // BLOCK_BYTES), least), max(-(-size // BUCKET_BYTES), least)
    dealt = rows.withColumn("block", F.pmod(F.xxhash64("id", "text"), F.lit(blocks)).cast("int"))
    replies = settle(dealt.groupBy("block").applyInArrow(_request(order, buckets), REQUEST).groupBy("level", "bucket").applyInArrow(_reply, REPLY), "ngram-counts")
    v, n = (x or 0 for x in replies.where("level = 0").agg(F.sum("distinct"), F.sum("tokens")).first())
    learn, shape = _histogram(order, n, v)
    names = shape.replace(",", "").split()[::2]
    keys = names[: 2 * (order - 1)]
    table = dealt.groupBy("block").cogroup(replies.groupBy("block")).applyInArrow(learn, shape).groupBy(*keys).agg(*[F.sum(c).alias(c) for c in names[len(keys):]]).toArrow()
    cell = {c: table.column(c).to_numpy() for c in names}
    weights = learn_weights(cell["n"], [cell[f"r{k}"] / np.maximum(cell["n"], 1) for k in range(1, order)], [cell[f"c{k}"].astype(np.int64) for k in range(1, order)])
    out = dealt.groupBy("block").cogroup(replies.groupBy("block")).applyInArrow(_scores(order, n, v, weights), "id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    return out.select(F.col("id").alias(id_col), "held_out", "n_tokens", "n_known", F.lit(n).cast("long").alias("train_tokens"), "base_score", "score")
