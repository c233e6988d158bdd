"""The word model on whole documents: a row a document, with arrays over its tokens.

Rows of documents are (block, doc_id, chunk, pos, toks, z): chunk number, place in the chunk, word and topic of each token in order.
A block is a share of the documents with a dictionary of its own, so that words travel once a block and not once a token:
a block's counts are added up over all blocks by word, and go back to the blocks that hold the word.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.io import discard, settle
from .topics import block_labels, block_of

#: Tokens that a block holds, more where a document has more; tokens whose weights, and whose hashes, are in memory at one time.
BLOCK_TOKENS, SLICE, HASHED = 500_000, 65_536, 16_384

DOCS = "block int, doc_id long, chunk array<int>, pos array<int>, toks array<string>, z array<int>"
#: Rows of documents, with ids in place of words, and rows of a block's dictionary (word not null) with the word's counts by topic.
CODED = "block int, doc_id long, chunk array<int>, pos array<int>, ids array<int>, z array<int>, word string, id int, counts array<long>"
_INTS = pa.list_(pa.int32())
_CODED = pa.schema([("block", pa.int32()), ("doc_id", pa.int64()), ("chunk", _INTS), ("pos", _INTS), ("ids", _INTS), ("z", _INTS), ("word", pa.string()), ("id", pa.int32()), ("counts", pa.list_(pa.int64()))])
#: Documents of a batch that goes back to Spark.
SENT = 2_000


def numbers(a: pa.Array | pa.ChunkedArray) -> np.ndarray:
    return a.to_numpy(zero_copy_only=False) if isinstance(a, pa.Array) else a.to_numpy()


def flat(table: pa.Table, column: str) -> pa.Array:
    """The inner values of a list column as one array."""
    a = table.column(column).combine_chunks()
    a = a if isinstance(a, pa.Array) else pa.concat_arrays(a.chunks)
    return a.flatten()


def lengths(table: pa.Table, column: str) -> np.ndarray:
    a = table.column(column).combine_chunks()
    return numbers(pc.list_value_length(a)).astype(np.int64)


def listed(values: pa.Array | np.ndarray, sizes: np.ndarray) -> pa.Array:
    """A list array of rows of the given sizes."""
    values = values if isinstance(values, pa.Array) else pa.array(values.astype(np.int32))
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), values)


def _leading(text: pa.Array) -> np.ndarray:
    """The first 32 bits, as 8 hex digits read them, of the MD5 of texts of up to 55 bytes, many at once: RFC 1321 on one block."""
    n, flat_bytes = len(text), np.frombuffer(text.buffers()[2] or b"", np.uint8)
    at = np.frombuffer(text.buffers()[1], np.int32)[: n + 1].astype(np.int64)
    size = np.diff(at)
    if size.max(initial=0) > 55:
        raise ValueError("a text of more than 55 bytes")
    block = np.zeros((n, 64), np.uint8)
    block.ravel()[np.arange(at[-1]) + np.repeat(np.arange(n) * 64 - at[:-1], size)] = flat_bytes[: at[-1]]
    block[np.arange(n), size] = 0x80
    words = np.ascontiguousarray(block.view("<u4").T)
    words[14] = size * 8
    start = [np.full(n, x, np.uint32) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]
    a, b, c, d = start
    for i in range(64):
        if i < 16:
            f, g = d ^ (b & (c ^ d)), i
        elif i < 32:
            f, g = c ^ (d & (b ^ c)), (5 * i + 1) % 16
        elif i < 48:
            f, g = b ^ c ^ d, (3 * i + 5) % 16
        else:
            f, g = c ^ (b | ~d), 7 * i % 16
        f += a
        f += _SINES[i]
        if g < 14 and 4 * g <= int(size.max(initial=0)) or g == 14:  # the others are zero
            f += words[g]
        turn = _TURNS[i // 16][i % 4]
        a, d, c, b = d, c, b, b + ((f << turn) | (f >> np.uint32(32 - turn)))
    return (a + start[0]).byteswap()


_SINES = [np.uint32(int(abs(math.sin(i + 1)) * 2**32)) for i in range(64)]
_TURNS = [[np.uint32(x) for x in xs] for xs in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))]


def uniforms(seed: int, sweep: int, docs: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """``topics.uniform`` of tokens 0, 1, 2, ... of each document."""
    out = np.empty(int(sizes.sum()))
    doc, g = np.repeat(docs.astype(np.int64), sizes), np.arange(len(out)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    for begin in range(0, len(out), HASHED):
        on = slice(begin, begin + HASHED)
        text = pc.binary_join_element_wise(f"{seed}|{sweep}", pa.array(doc[on]).cast(pa.string()), pa.array(g[on]).cast(pa.string()), "|")
        out[on] = _leading(text)
    return out / 4294967296.0


def _coded(block: int, docs: pa.Table, sizes: np.ndarray, ids: np.ndarray, z: np.ndarray, words: pa.Array, n_topics: int) -> Iterator[pa.RecordBatch]:
    """Rows of a block's documents (doc_id, chunk, pos) and of its dictionary with counts."""
    n = len(sizes)
    counts = np.bincount(ids.astype(np.int64) * n_topics + z, minlength=len(words) * n_topics)
    held = {"block": pa.array(np.full(n, block, np.int32)), **{c: docs.column(c).cast(_CODED.field(c).type) for c in ("doc_id", "chunk", "pos")}, "ids": listed(ids, sizes), "z": listed(z, sizes)}
    table = pa.table({f.name: held.get(f.name, pa.nulls(n, f.type)) for f in _CODED}, schema=_CODED)
    yield from table.combine_chunks().to_batches(SENT)
    m = len(words)
    held = {"block": pa.array(np.full(m, block, np.int32)), "word": words, "id": pa.array(np.arange(m, dtype=np.int32)), "counts": pa.ListArray.from_arrays(pa.array((np.arange(m + 1) * n_topics).astype(np.int32)), pa.array(counts.astype(np.int64)))}
    yield from pa.table({f.name: held.get(f.name, pa.nulls(m, f.type)) for f in _CODED}, schema=_CODED).to_batches(50_000)


def _start(n_topics: int, seed: int, labels: list[int], coded: bool):
    """The chunks of a partition, which is a block, as rows of documents with topics before the first sweep."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [b for b in batches if b.num_rows]
        if not rows:
            return
        part = TaskContext.get().partitionId()
        block = labels[part] if part < len(labels) else 32 * len(labels) + part
        table = pa.Table.from_batches(rows).sort_by([("doc_id", "ascending"), ("chunk_no", "ascending")])
        sizes, docs, toks = lengths(table, "toks"), numbers(table.column("doc_id")), flat(table, "toks")
        first = np.flatnonzero(np.concatenate([[True], docs[1:] != docs[:-1]]))
        of_doc = np.add.reduceat(sizes, first)
        pos = np.arange(len(toks)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        z = np.floor(uniforms(seed, 0, docs[first], of_doc) * n_topics).astype(np.int32)
        own = pa.table({"doc_id": pa.array(docs[first]), "chunk": listed(np.repeat(numbers(table.column("chunk_no")), sizes), of_doc), "pos": listed(pos, of_doc)})
        if coded:
            code = toks.dictionary_encode()
            yield from _coded(block, own, of_doc, numbers(code.indices), z, code.dictionary, n_topics)
        else:
            yield from pa.table({"block": pa.array(np.full(len(first), block, np.int32)), **{c: own.column(c) for c in own.column_names}, "toks": listed(toks, of_doc), "z": listed(z, of_doc)}).combine_chunks().to_batches(SENT)

    return run


def _sweep(n_topics: int, totals: list[int], v: int, doc_prior: float, word_prior: float, seed: int, sweep: int, last: bool):
    """New topics of a block's tokens from the counts before the sweep: the first topic whose cumulated share passes the uniform number."""

    def run(key: tuple[pa.Scalar, ...], docs: pa.Table, words: pa.Table) -> pa.Table:
        docs, words = docs.sort_by("doc_id"), words.sort_by("id")
        sizes, ids, z = lengths(docs, "ids"), numbers(flat(docs, "ids")), numbers(flat(docs, "z")).astype(np.int32)
        doc = np.repeat(np.arange(len(sizes)), sizes)
        of_doc = doc_prior + np.bincount(doc * n_topics + z, minlength=len(sizes) * n_topics).reshape(-1, n_topics)
        of_word = word_prior + numbers(flat(words, "n")).reshape(-1, n_topics)
        total = word_prior * v + np.array(totals, float)
        u = uniforms(seed, sweep, numbers(docs.column("doc_id")), sizes)
        new = np.empty(len(z), np.int32)
        for begin in range(0, len(z), SLICE):
            on = slice(begin, begin + SLICE)
            d, w, old = doc[on], ids[on], z[on]
            p = of_doc[d] * of_word[w] / total
            # the token itself is not counted
            p[np.arange(len(old)), old] = (of_doc[d, old] - 1) * (of_word[w, old] - 1) / (total[old] - 1)
            sums = np.cumsum(p, axis=1)
            new[on] = np.minimum((sums / sums[:, -1:] <= u[on, None]).sum(1), n_topics - 1)
        if not last:
            return pa.Table.from_batches(_coded(key[0].as_py(), docs, sizes, ids, new, words.column("word").combine_chunks(), n_topics), _CODED)
        named = words.column("word").combine_chunks().take(pa.array(ids))
        return pa.table({**{c: docs.column(c) for c in ("block", "doc_id", "chunk", "pos")}, "toks": listed(named, sizes), "z": listed(new, sizes)})

    return run


def _blocks(chunks: DataFrame) -> tuple[int, list[int]]:
    tokens = chunks.agg(F.sum(F.size("toks"))).first()[0] or 0
    n = max(8, -(-tokens // BLOCK_TOKENS))
    return n, block_labels(chunks.sparkSession, n)


def start(chunks: DataFrame, n_topics: int, seed: int = 7) -> DataFrame:
    """Rows of documents with the topics of ``topics.init``."""
    n, labels = _blocks(chunks)
    return settle(chunks.select("doc_id", "chunk_no", "toks").repartition(n, "doc_id").mapInArrow(_start(n_topics, seed, labels, False), DOCS), "word-docs")


def snapshot(chunks: DataFrame, n_topics: int, sweeps: int, seed: int = 7, doc_prior: float = 0.5, word_prior: float = 0.01) -> DataFrame:
    """Rows of documents after snapshot sweeps of the word model: the draws of ``topics.snapshot_sweep`` over one-word cliques."""
    if not sweeps:
        return start(chunks, n_topics, seed)
    n, labels = _blocks(chunks)
    now = settle(chunks.select("doc_id", "chunk_no", "toks").repartition(n, "doc_id").mapInArrow(_start(n_topics, seed, labels, True), CODED), "word-blocks")
    v = now.where("word is not null").select("word").distinct().count()
    for s in range(1, sweeps + 1):
        held = now.where("word is not null").select("block", "word", "id", "counts")
        totals = list(held.agg(*[F.sum(F.col("counts")[k]) for k in range(n_topics)]).first())
        same = Window.partitionBy("word")
        words = held.select("block", "word", "id", F.array(*[F.sum(F.col("counts")[k]).over(same) for k in range(n_topics)]).alias("n"))
        docs = now.where("word is null").select("block", "doc_id", "chunk", "pos", "ids", "z")
        sides = docs.repartition(n, "block").groupBy("block"), words.repartition(n, "block").groupBy("block")
        last = s == sweeps
        work = _sweep(n_topics, [t or 0 for t in totals], v, doc_prior, word_prior, seed, s, last)
        before, now = now, settle(sides[0].cogroup(sides[1]).applyInArrow(work, DOCS if last else CODED), "word-docs" if last else f"word-sweep-{s}")
        discard(before)
    return now


#: Rows of documents of cliques (word ids and cliques' lengths in order, a topic a clique), and rows of a block's dictionary as above.
CLIQUES = "block int, doc_id long, ids array<int>, lens array<int>, z array<int>, word string, id int, counts array<long>"
_CLIQUES = pa.schema([("block", pa.int32()), ("doc_id", pa.int64()), ("ids", _INTS), ("lens", _INTS), ("z", _INTS), ("word", pa.string()), ("id", pa.int32()), ("counts", pa.list_(pa.int64()))])
STATE = "doc_id long, g int, words array<string>, z int"


def _coded_cliques(block: int, docs: np.ndarray, sizes: np.ndarray, lens: np.ndarray, ids: np.ndarray, z: np.ndarray, words: pa.Array, n_topics: int) -> Iterator[pa.RecordBatch]:
    """Rows of a block's documents, of ``sizes`` cliques each, and of its dictionary with counts."""
    n, m = len(sizes), len(words)
    owner = np.repeat(np.arange(n), sizes)
    tokens = np.bincount(owner, weights=lens, minlength=n).astype(np.int64)
    counts = np.bincount(ids.astype(np.int64) * n_topics + np.repeat(z, lens), minlength=m * n_topics)
    held = {"block": pa.array(np.full(n, block, np.int32)), "doc_id": pa.array(docs), "ids": listed(ids, tokens), "lens": listed(lens, sizes), "z": listed(z, sizes)}
    yield from pa.table({f.name: held.get(f.name, pa.nulls(n, f.type)) for f in _CLIQUES}, schema=_CLIQUES).to_batches(SENT)
    held = {"block": pa.array(np.full(m, block, np.int32)), "word": words, "id": pa.array(np.arange(m, dtype=np.int32)), "counts": pa.ListArray.from_arrays(pa.array((np.arange(m + 1) * n_topics).astype(np.int32)), pa.array(counts.astype(np.int64)))}
    yield from pa.table({f.name: held.get(f.name, pa.nulls(m, f.type)) for f in _CLIQUES}, schema=_CLIQUES).to_batches(50_000)


def _start_cliques(n_topics: int, seed: int, labels: list[int]):
    """The phrases of a partition, which is a block, as rows of documents with topics before the first sweep."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = []
        for b in batches:
            if b.num_rows:  # a phrase is kept once for each batch
                rows.append(pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2).dictionary_encode()], ["doc_id", "g", "phrase"]))
        if not rows:
            return
        part = TaskContext.get().partitionId()
        block = labels[part] if part < len(labels) else 32 * len(labels) + part
        table = pa.Table.from_batches(rows).unify_dictionaries().combine_chunks()
        docs, g = numbers(table.column("doc_id")), numbers(table.column("g"))
        phrase = table.column("phrase").combine_chunks()
        phrase = phrase if isinstance(phrase, pa.Array) else phrase.chunk(0)
        order = np.lexsort((g, docs))
        docs = docs[order]
        first = np.flatnonzero(np.concatenate([[True], docs[1:] != docs[:-1]]))
        sizes = np.diff(np.append(first, len(docs)))
        split = pc.split_pattern(phrase.dictionary, " ")
        code = split.flatten().dictionary_encode()
        of_phrase = pa.ListArray.from_arrays(split.offsets, code.indices).take(phrase.indices.take(pa.array(order)))
        lens, ids = numbers(pc.list_value_length(of_phrase)).astype(np.int64), numbers(of_phrase.flatten())
        z = np.floor(uniforms(seed, 0, docs[first], sizes) * n_topics).astype(np.int32)
        yield from _coded_cliques(block, docs[first], sizes, lens, ids, z, code.dictionary, n_topics)

    return run


def _passed(p: np.ndarray, u: np.ndarray) -> np.ndarray:
    """The first topic whose cumulated share passes the uniform number."""
    sums = np.cumsum(p, axis=1)
    return np.minimum((sums / sums[:, -1:] <= u[:, None]).sum(1), p.shape[1] - 1)


def _sweep_cliques(n_topics: int, totals: list[int], v: int, doc_prior: float, word_prior: float, seed: int, sweep: int, last: bool):
    """New topics of a block's cliques from the counts before the sweep, as ``topics.clique_weights`` has them."""

    def run(key: tuple[pa.Scalar, ...], docs: pa.Table, words: pa.Table) -> pa.Table:
        docs, words = docs.sort_by("doc_id"), words.sort_by("id")
        sizes, ids, lens, z = lengths(docs, "z"), numbers(flat(docs, "ids")), numbers(flat(docs, "lens")).astype(np.int64), numbers(flat(docs, "z")).astype(np.int32)
        doc, at = np.repeat(np.arange(len(sizes)), sizes), np.cumsum(lens) - lens
        of_doc = doc_prior + np.bincount(doc * n_topics + z, weights=lens, minlength=len(sizes) * n_topics).reshape(-1, n_topics)
        of_word = word_prior + numbers(flat(words, "n")).reshape(-1, n_topics)
        total = word_prior * v + np.array(totals, float)
        u = uniforms(seed, sweep, numbers(docs.column("doc_id")), sizes)
        new = np.empty(len(z), np.int32)
        one, long = np.flatnonzero(lens == 1), np.flatnonzero(lens > 1)
        for begin in range(0, len(one), SLICE):
            c = one[begin : begin + SLICE]
            d, w, old = doc[c], ids[at[c]], z[c]
            p = of_doc[d] * of_word[w] / total
            # the clique itself is not counted
            p[np.arange(len(c)), old] = (of_doc[d, old] - 1) * (of_word[w, old] - 1) / (total[old] - 1)
            new[c] = _passed(p, u[c])
        share = np.cumsum(lens[long]) // SLICE
        for c in np.split(long, np.flatnonzero(np.diff(share)) + 1) if len(long) else []:
            n = lens[c]
            head = np.cumsum(n) - n
            of, j = np.repeat(np.arange(len(c)), n), np.arange(n.sum()) - np.repeat(head, n)
            w = ids[np.repeat(at[c], n) + j].astype(np.int64)
            # earlier copies of a word in its clique, and all of them
            order = np.lexsort((w, of))
            begun = np.concatenate([[True], (w[order][1:] != w[order][:-1]) | (of[order][1:] != of[order][:-1])])
            run_of, earlier, copies = np.cumsum(begun) - 1, np.empty(len(w)), np.empty(len(w))
            earlier[order] = np.arange(len(w)) - np.flatnonzero(begun)[run_of]
            copies[order] = np.bincount(run_of)[run_of]
            own = np.zeros((len(w), n_topics))
            own[np.arange(len(w)), z[c][of]] = 1
            gone = own * n[of][:, None] - j[:, None]
            logs = np.log(of_doc[doc[c]][of] - gone) + np.log(of_word[w] - own * copies[:, None] + earlier[:, None]) - np.log(total - gone)
            sums = np.add.reduceat(logs, head, axis=0)
            new[c] = _passed(np.exp(sums - sums.max(1, keepdims=True)), u[c])
        named = words.column("word").combine_chunks()
        if not last:
            return pa.Table.from_batches(_coded_cliques(key[0].as_py(), numbers(docs.column("doc_id")), sizes, lens, ids, new, named, n_topics), _CLIQUES)
        g = np.arange(len(z)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        return pa.table({"doc_id": pa.array(np.repeat(numbers(docs.column("doc_id")), sizes)), "g": pa.array(g.astype(np.int32)), "words": listed(named.take(pa.array(ids)), lens), "z": pa.array(new)})

    return run


def snapshot_cliques(parts: DataFrame, n_topics: int, sweeps: int, seed: int = 7, doc_prior: float = 0.5, word_prior: float = 0.01) -> DataFrame:
    """doc_id, g, words, z after one snapshot sweep or more of the clique model: the draws of ``topics.init`` and ``topics.snapshot_sweep``.
    parts (doc_id, g, len, phrase) has no null doc_id and numbers a document's phrases from 0."""
    n = max(8, -(-(parts.agg(F.sum("len")).first()[0] or 0) // BLOCK_TOKENS))
    labels = block_labels(parts.sparkSession, n)
    now = settle(parts.select("doc_id", "g", "phrase").repartition(n, "doc_id").mapInArrow(_start_cliques(n_topics, seed, labels), CLIQUES), "clique-blocks")
    v = now.where("word is not null").select("word").distinct().count()
    for s in range(1, sweeps + 1):
        held = now.where("word is not null").select("block", "word", "id", "counts")
        totals = list(held.agg(*[F.sum(F.col("counts")[k]) for k in range(n_topics)]).first())
        same = Window.partitionBy("word")
        words = held.select("block", "word", "id", F.array(*[F.sum(F.col("counts")[k]).over(same) for k in range(n_topics)]).alias("n"))
        docs = now.where("word is null").select("block", "doc_id", "ids", "lens", "z")
        sides = docs.repartition(n, "block").groupBy("block"), words.repartition(n, "block").groupBy("block")
        last = s == sweeps
        work = _sweep_cliques(n_topics, [t or 0 for t in totals], v, doc_prior, word_prior, seed, s, last)
        before, now = now, settle(sides[0].cogroup(sides[1]).applyInArrow(work, STATE if last else CLIQUES), f"swept-{s}")
        discard(before)
    return now


def pack(tokens: DataFrame) -> DataFrame:
    """Rows of documents of token rows (doc_id, chunk_no, pos, word, z)."""
    item = F.struct(F.col("chunk_no").cast("int").alias("chunk_no"), F.col("pos").cast("int").alias("pos"), "word", F.col("z").cast("int").alias("z"))
    docs = tokens.groupBy("doc_id").agg(F.array_sort(F.collect_list(item)).alias("t"))
    n = max(8, -(-tokens.count() // BLOCK_TOKENS))
    part = lambda c: F.transform("t", lambda t: t[c])
    return settle(docs.select(block_of("doc_id", block_labels(tokens.sparkSession, n), n).alias("block"), "doc_id", part("chunk_no").alias("chunk"), part("pos").alias("pos"), part("word").alias("toks"), part("z").alias("z")), "word-docs")


def rows(docs: DataFrame) -> DataFrame:
    """doc_id, chunk_no, pos, g, word, z: a row a token."""
    long = docs.select("doc_id", F.posexplode(F.arrays_zip("chunk", "pos", "toks", "z")).alias("g", "t"))
    return long.select("doc_id", F.col("t.chunk").alias("chunk_no"), F.col("t.pos").alias("pos"), "g", F.col("t.toks").alias("word"), F.col("t.z").alias("z"))


def inner(table: pa.Table) -> np.ndarray:
    """Whether a token has one before it in its chunk."""
    sizes, chunk = lengths(table, "chunk"), numbers(flat(table, "chunk"))
    same = np.zeros(len(chunk), bool)
    same[1:] = chunk[1:] == chunk[:-1]
    first = (np.cumsum(sizes) - sizes)[sizes > 0]
    same[first] = False
    return same


def _pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        table = pa.Table.from_batches([batch])
        code, z = flat(table, "toks").dictionary_encode(), numbers(flat(table, "z")).astype(np.int64)
        block = np.repeat(numbers(table.column("block")), lengths(table, "toks"))
        w, at = numbers(code.indices).astype(np.int64), np.flatnonzero(inner(table))
        at = at[z[at] == z[at - 1]]
        for b in np.unique(block[at]):
            on = at[block[at] == b]
            size = len(code.dictionary)
            # topics are few, so they lead: the key stays within 64 bits
            keys, n = np.unique((z[on] * size + w[on - 1]) * size + w[on], return_counts=True)
            rest, right = np.divmod(keys, size)
            k, left = np.divmod(rest, size)
            take = code.dictionary.take
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), b, np.int32)), take(pa.array(left)), take(pa.array(right)), pa.array(k.astype(np.int32)), pa.array(n)], ["block", "v", "w", "k", "n"])


def block_pairs(docs: DataFrame) -> DataFrame:
    """block, v, w, k, n: neighbours in a chunk that share a topic, counted within batches."""
    return docs.select("block", "chunk", "toks", "z").mapInArrow(_pairs, "block int, v string, w string, k int, n long")


def adjacent_pairs(docs: DataFrame) -> DataFrame:
    """v, w, k, n: neighbours in a chunk that share a topic."""
    return block_pairs(docs).groupBy("v", "w", "k").agg(F.sum("n").alias("n"))


def merged(key: tuple[pa.Scalar, ...], docs: pa.Table, pairs: pa.Table) -> pa.Table:
    """A block's documents (DOCS) with the neighbours of one topic joined whose (k, v, w) is listed: in a run of joinable neighbours every
    second join counts, from left to right, so none overlaps."""
    docs = docs.sort_by("doc_id")
    sizes, toks, z = lengths(docs, "toks"), flat(docs, "toks"), numbers(flat(docs, "z")).astype(np.int64)
    code = toks.dictionary_encode()
    w, size = numbers(code.indices).astype(np.int64), len(code.dictionary)
    place = lambda c: numbers(pc.index_in(pairs.column(c).combine_chunks(), value_set=code.dictionary)).astype(np.int64)
    keys = np.sort((numbers(pairs.column("k")).astype(np.int64) * size + place("v")) * size + place("w")) if pairs.num_rows else np.zeros(0, np.int64)
    at = np.flatnonzero(inner(docs))
    at = at[z[at] == z[at - 1]]
    join, i = np.zeros(len(w), bool), np.arange(len(w))
    join[at[np.isin((z[at] * size + w[at - 1]) * size + w[at], keys)] - 1] = True
    begins = join & ~np.concatenate([[False], join[:-1]])
    join &= (i - np.maximum.accumulate(np.where(begins, i, 0))) % 2 == 0
    keep = np.flatnonzero(~np.concatenate([[False], join[:-1]]))
    left = np.bincount(np.repeat(np.arange(len(sizes)), sizes)[keep], minlength=len(sizes))
    phrases = pc.binary_join(listed(toks, 1 + join[keep].astype(np.int64)), " ")
    kept = {c: listed(numbers(flat(docs, c))[keep], left) for c in ("chunk", "pos", "z")}
    return pa.table({"block": docs.column("block"), "doc_id": docs.column("doc_id"), "chunk": kept["chunk"], "pos": kept["pos"], "toks": listed(phrases, left), "z": kept["z"]})


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for begin in range(0, batch.num_rows, SENT):
            table = pa.Table.from_batches([batch.slice(begin, SENT)])
            sizes, toks, z = lengths(table, "toks"), flat(table, "toks"), numbers(flat(table, "z"))
            fresh = numbers(flat(table, "x")) == 0
            doc = np.repeat(np.arange(len(sizes)), sizes)
            run = np.cumsum(fresh)
            # counted in the document; a document that begins with a glued token begins with run 0
            before = np.concatenate([[0], run])[np.cumsum(sizes) - sizes]
            run = run - np.repeat(before, sizes)
            head = np.flatnonzero(fresh | np.concatenate([[True], doc[1:] != doc[:-1]])) if len(doc) else np.zeros(0, np.int64)
            length = np.diff(np.append(head, len(doc)))
            phrase = pc.binary_join(listed(toks, length), " ")
            ends = head + length - 1
            yield pa.RecordBatch.from_arrays([table.column("doc_id").combine_chunks().take(pa.array(doc[head])), pa.array(run[head].astype(np.int64)), phrase, pa.array(length.astype(np.int32)), pa.array(z[ends].astype(np.int32))], ["doc_id", "run", "phrase", "len", "z"])


def glued_runs(docs: DataFrame) -> DataFrame:
    """doc_id, run, phrase, len, z: maximal runs of a head and the tokens glued to their left neighbour, of documents (doc_id, toks, z, x)
    with x = 1 for a glued token; the topic is that of the last word."""
    return docs.select("doc_id", "toks", "z", "x").mapInArrow(_runs, "doc_id long, run long, phrase string, len int, z int")


def same_topic(docs: DataFrame) -> DataFrame:
    """doc_id, toks, z, x: a token is glued to its left neighbour in the chunk where both have one topic."""
    x = F.transform("pos", lambda p, i: F.when((p > 0) & (F.get("z", i) == F.get("z", i - 1)), 1).otherwise(0))
    return docs.select("doc_id", "toks", "z", x.alias("x"))
