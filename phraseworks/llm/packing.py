"""Vector best-fit packing of token sequences.

A piece asks for tokens, one document place and an attention cost (the square of its length); a bin has a capacity of
each. Pieces come longest first; among the open bins that hold a piece in every dimension the one with the smallest
weighted norm of what would remain (or the largest weighted dot-product of demand and residual) takes it.

Pieces are dealt to tasks of bounded size by a hash. Bins that a task fills to ``CLOSE`` of the tokens are final; the
pieces of its other bins meet again in fewer tasks, until one task holds all that is left.

Edge cases: null text is empty and still is one piece of length 1 (its end id); texts of any length are tokenised whole, and the
string of a special token in them is that token; only documents over the capacity are cut, the short piece first; repeated
rows are packed each; rows with a null id are packed under it; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import json
import zlib
from bisect import bisect_left, insort
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows, settle

TASK_PIECES, LEAST_TASKS, CLOSE = 100_000, 32, 0.995


def byte_letters() -> dict[str, int]:
    """The printable stand-ins of bytes in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


@lru_cache(maxsize=4)
def encoder(path: str, special: bool = True):
    """Function from texts to id lists for a tokenizer file, as its library gives them with add_special_tokens=False: none is put
    before or behind, but the string of a special token in a text is that token; with special=False it is ordinary text. A
    byte-level file whose merges are in the order of their ids is run by the faster rank-based encoder, which then gives the
    same ids; texts that hold a special token's string, and all texts of any other file, by the file's own library."""
    import tiktoken
    from tokenizers import Tokenizer

    with open(path) as f:
        spec = json.load(f)
    model, pre = spec["model"], spec.get("pre_tokenizer") or {}
    letters, vocab = byte_letters(), model.get("vocab", {})
    merges = [m if isinstance(m, str) else " ".join(m) for m in model.get("merges", [])]
    made = [vocab.get(m.replace(" ", "")) for m in merges]
    own = Tokenizer.from_file(path)
    own.encode_special_tokens = not special
    by_library = lambda texts: [x.ids for x in own.encode_batch(texts, add_special_tokens=False)]
    ranked = model.get("type") == "BPE" and pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and not spec.get("normalizer") and None not in made and made == sorted(set(made))
    added = {t["content"] for t in spec.get("added_tokens", [])}
    plain = all(t.get("special") for t in spec.get("added_tokens", []))
    if ranked and plain:
        ranks = {bytes(letters[c] for c in w): i for w, i in vocab.items() if w not in added}
        pattern = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""  # fixed value of the byte-level pre-tokenizer
        if len(ranks) == 256 + len(merges):
            fast = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
            marks = added if special else ()
            return lambda texts: [by_library([t])[0] if any(m in t for m in marks) else fast.encode_ordinary(t) for t in texts]
    return by_library


PIECE = "doc_id long, piece int, start long, length long, ids_crc32 long"


def pieces(docs: DataFrame, path: str, capacity: int = 1024, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces of at most ``capacity`` tokens: doc_id, piece, start, length, ids_crc32."""

    def make():
        encode = encoder(path)

        def work(keys, texts):
            rows = []
            for key, ids in zip(keys, encode([t or "" for t in texts]), strict=True):
                data = np.array([*ids, end_id], dtype="<u4")
                head = len(data) % capacity or min(capacity, len(data))
                cuts = [0, *range(head, len(data) + 1, capacity)]
                rows += [(key, i, a, b - a, zlib.crc32(data[a:b].tobytes())) for i, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False))]
            return {n: list(c) for n, c in zip(("doc_id", "piece", "start", "length", "ids_crc32"), zip(*rows, strict=True), strict=True)}

        return work

    return map_rows(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), make, PIECE)


class VectorBestFit:
    """Open bins by residual tokens, and among those by residual places and attention cost."""

    def __init__(self, capacity: tuple[int, int, int], weights: tuple[float, float, float] = (1.0, 0.05, 0.05), rule: str = "norm") -> None:
        self.capacity, self.weights, self.rule = capacity, weights, rule
        self.open: dict[int, dict[tuple[int, int], list[int]]] = {}
        self.levels: list[int] = []
        self.used: list[int] = []

    def _keep(self, bin_: int, left: tuple[int, int, int]) -> None:
        if left[0] not in self.open:
            self.open[left[0]] = {}
            insort(self.levels, left[0])
        self.open[left[0]].setdefault(left[1:], []).append(bin_)

    def add(self, tokens: int, docs: int, cost: int) -> tuple[int, int]:
        """Place a demand; its bin and the token offset there."""
        (ct, cd, ca), (wt, wd, wa) = self.capacity, self.weights
        at, value = None, None
        levels = self.levels[bisect_left(self.levels, tokens) :]
        for r in levels if self.rule == "norm" else reversed(levels):
            part = wt * ((r - tokens) / ct) ** 2
            if self.rule == "norm" and value is not None and part >= value:
                break
            for d, a in self.open[r]:
                if d >= docs and a >= cost:
                    v = part + wd * ((d - docs) / cd) ** 2 + wa * ((a - cost) / ca) ** 2 if self.rule == "norm" else -(wt * tokens * r / ct**2 + wd * docs * d / cd**2 + wa * cost * a / ca**2)
                    if value is None or v < value:
                        at, value = (r, d, a), v
        if at is None:
            bin_, at = len(self.used), self.capacity
            self.used.append(0)
        else:
            same = self.open[at[0]][at[1:]]
            bin_ = same.pop()
            if not same:
                del self.open[at[0]][at[1:]]
                if not self.open[at[0]]:
                    del self.open[at[0]]
                    self.levels.pop(bisect_left(self.levels, at[0]))
        offset = self.used[bin_]
        self.used[bin_] += tokens
        left = (at[0] - tokens, at[1] - docs, at[2] - cost)
        if left[0]:
            self._keep(bin_, left)
        return bin_, offset


def _packer(limits: tuple[int, int, int], rule: str, step: int, last: bool):
    """The work of one task of one round; the same rows in any order give the same bins."""

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        table = table.sort_by([("length", "descending"), ("doc_id", "ascending"), ("piece", "ascending"), ("ids_crc32", "ascending")])
        bins = VectorBestFit(limits, rule=rule)
        spots = [bins.add(x, 1, x * x) for x in table.column("length").to_pylist()]
        final = [last or bins.used[b] >= CLOSE * limits[0] for b, _ in spots]
        base = (step << 56) | (key[0].as_py() << 32)
        out = table.drop_columns(["task"])
        for name, values in (("sequence_id", [base | b for b, _ in spots]), ("offset", [o for _, o in spots])):
            out = out.append_column(name, pa.array(values, pa.int64()))
        return out.append_column("final", pa.array(final, pa.bool_()))

    return run


def pack(parts: DataFrame, capacity: int = 1024, max_docs: int | None = None, max_cost: int | None = None, rule: str = "norm") -> DataFrame:
    """parts with sequence_id and offset. Without own limits, a sequence may hold as many documents and as much attention cost
    as its tokens allow. A piece over a limit by itself gets a sequence of its own."""
    limits = (capacity, max_docs or capacity, max_cost or capacity * capacity)
    names, rows, done, before = parts.columns, settle(parts, "pieces"), None, None
    for step in range(100):
        n = rows.count()
        tasks = max(-(-n // TASK_PIECES), min(LEAST_TASKS, -(-n // 64)) if step == 0 else 1, 1)
        # where other limits than tokens bind, bins stay open however often their pieces meet again: then they are final as they are
        last, before = tasks == 1 or (before is not None and n > 0.7 * before), n

        dealt = rows.select(F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32", F.lit(step)), F.lit(tasks)).cast("int").alias("task"), *names)
        packed = settle(dealt.groupBy("task").applyInArrow(_packer(limits, rule, step, last), f"{PIECE}, sequence_id long, offset long, final boolean"), "packed")
        closed = packed.where("final").drop("final")
        done = closed if done is None else done.unionByName(closed)
        if last:
            return done
        rows = packed.where("not final").select(*names)
    raise RuntimeError("packing did not come to an end")


def pack_documents(docs: DataFrame, path: str, capacity: int = 1024, end_id: int = 2, max_docs: int | None = None, max_cost: int | None = None, rule: str = "norm", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset for every piece of every document."""
    return pack(pieces(docs, path, capacity, end_id, id_col, text_col), capacity, max_docs, max_cost, rule)
