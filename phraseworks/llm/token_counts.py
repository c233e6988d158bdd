"""Edit-aware token counts: a segment tree over the pre-tokens of each document.

A leaf holds pre-tokens with their lengths and token counts, an inner node the sums below it. An edit encodes again
only the pre-tokens that it touches, those of a run of blanks before it, and those behind it up to the first old border that
the new text shares; then the sums on the way to the root are corrected. The total is the root's sum.

Edge cases: null text is empty and counts 0; an empty document takes edits at 0; edits with null or out-of-range
offsets are cut to the text; edits apply in order, each to the text the earlier ones left; repeated document rows get
the same edits each; edits of unknown documents have no effect; documents with a null id are counted and take no edits; an
empty table gives no rows; other columns are not read, whatever their names.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .byte_bpe import ByteBpe, from_file
from .common import map_rows


class PieceTree:
    """Token counts of one text under edits."""

    def __init__(self, bpe: ByteBpe, text: str) -> None:
        self.bpe, self.text, self.reencoded = bpe, text, 0
        pieces = bpe.find(text)
        self._build([*map(len, pieces)], bpe.counts(pieces))

    def _build(self, chars: list[int], tokens: list[int]) -> None:
        """A leaf for each pre-token; a leaf that edits have changed is in ``changed`` with its pre-tokens."""
        self.width = 1 << max(0, len(chars) - 1).bit_length()
        self.changed: dict[int, list[tuple[int, int]]] = {}
        levels = [np.zeros((self.width, 2), np.int64)]
        levels[0][: len(chars), 0], levels[0][: len(tokens), 1] = chars, tokens
        while len(levels[-1]) > 1:
            levels.append(levels[-1].reshape(-1, 2, 2).sum(1))
        self.sums = np.concatenate([np.zeros((1, 2), np.int64), *levels[::-1]])

    def _pieces(self, leaf: int) -> list[tuple[int, int]]:
        got = self.changed.get(leaf)
        if got is None:
            size, tokens = self.sums[self.width + leaf].tolist()
            got = [(size, tokens)] if size else []
        return got

    @property
    def total(self) -> int:
        return int(self.sums[1, 1])

    def _leaf_at(self, offset: int) -> tuple[int, int]:
        """The leaf over the character ``offset`` and where that leaf starts."""
        node, start = 1, 0
        while node < self.width:
            node *= 2
            here = int(self.sums[node, 0])
            if offset >= start + here and self.sums[node + 1, 0]:
                start += here
                node += 1
        return node - self.width, start

    def _set(self, leaf: int, pieces: list[tuple[int, int]]) -> None:
        self.changed[leaf] = pieces
        node = leaf + self.width
        change = np.array([sum(p[0] for p in pieces), sum(p[1] for p in pieces)]) - self.sums[node]
        while node:
            self.sums[node] += change
            node //= 2

    def replace(self, start: int, end: int, new: str) -> None:
        start = max(0, min(start, len(self.text)))
        end = max(start, min(end, len(self.text)))
        shift = len(new) - (end - start)
        self.text = self.text[:start] + new + self.text[end:]
        # where a run of blanks is cut depends on what follows it, so the run before the edit is scanned anew as well
        back = start
        while back and self.text[back - 1].isspace():
            back -= 1
        first, begin = self._leaf_at(max(0, back - 1))
        fresh, scan = [], self.bpe.matches(self.text, begin)
        leaf, border = first, begin  # old pieces up to the old offset ``border`` are replaced
        at, kept = begin, []
        met = False
        while leaf < self.width and not met:
            for k, (size, _) in enumerate(self._pieces(leaf)):
                border += size
                while at < border + shift or at < start + len(new):
                    m = next(scan, None)
                    if m is None:
                        break
                    at = m.end()
                    fresh.append((at - m.start(), self.bpe.counts([m[0]])[0]))
                if border >= end and at == border + shift and at >= start + len(new):
                    kept, met = self._pieces(leaf)[k + 1 :], True
                    break
            leaf += 1
        if not met:
            fresh += [(m.end() - m.start(), self.bpe.counts([m[0]])[0]) for m in scan]
        self.reencoded += len(fresh)
        for other in range(first + 1, leaf):
            if self._pieces(other):
                self._set(other, [])
        self._set(first, fresh + kept)
        if len(self.changed[first]) > 64:
            flat = [p for leaf in range(self.width) for p in self._pieces(leaf)]
            self._build([p[0] for p in flat], [p[1] for p in flat])


def masking(rules: list[tuple[str, str, str]]) -> Callable[[str], list[tuple[int, int, str]]]:
    """Edits that put a replacement in place of every match of a pattern, first rule first, last match first. A rule
    is (pattern, replacement, a string that every match holds or ""): texts without that string need no search."""
    import re

    made = [(re.compile(p), r, needle) for p, r, needle in rules]

    def edits(text: str) -> list[tuple[int, int, str]]:
        spans: list[tuple[int, int, str]] = []
        for pattern, new, needle in made:
            for m in pattern.finditer(text) if needle in text else ():
                if m.end() > m.start() and all(m.end() <= a or m.start() >= b for a, b, _ in spans):
                    spans.append((m.start(), m.end(), new))
        return sorted(spans, reverse=True)

    return edits


def _run(bpe: ByteBpe, text: str, edits) -> tuple[int, int, int, int, str]:
    tree = PieceTree(bpe, text)
    before = tree.total
    for start, end, new in edits:
        tree.replace(len(tree.text) if start is None else start, len(tree.text) if end is None else end, new or "")
    return before, len(edits), tree.total, tree.reencoded, tree.text


COUNTS = "n_tokens long, n_edits long, n_tokens_after long, n_reencoded long"


def count_masked(docs: DataFrame, path: str, pattern: str, rules: list[tuple[str, str, str]], id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """Token counts before and after masking: id, n_tokens, n_edits, n_tokens_after, n_reencoded (pre-tokens encoded for the
    edits)[, text_after]."""

    def make():
        bpe, edits = from_file(path, pattern), masking(rules)

        def work(keys, texts):
            got = [_run(bpe, t or "", edits(t or "")) for t in texts]
            out = {id_col: keys} | {n: [g[i] for g in got] for i, n in enumerate(("n_tokens", "n_edits", "n_tokens_after", "n_reencoded"))}
            return out | ({"text_after": [g[4] for g in got]} if with_text else {})

        return work

    return map_rows(docs.select(F.col(id_col).cast("long").alias(id_col), F.col(text_col).cast("string").alias(text_col)), make, f"{id_col} long, {COUNTS}" + ", text_after string" * with_text)


def count_edited(docs: DataFrame, edits: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The same for a table of edits (id, seq, start_at, end_at, replacement); a null offset is the text's end (an append)."""
    script = edits.groupBy(F.col(id_col).alias("edit_of")).agg(F.sort_array(F.collect_list(F.struct("seq", "start_at", "end_at", "replacement"))).alias("script"))
    joined = docs.select(F.col(id_col).cast("long").alias(id_col), F.col(text_col).cast("string").alias(text_col)).join(script, F.col(id_col) == F.col("edit_of"), "left").select(id_col, text_col, "script")

    def make():
        bpe = from_file(path, pattern)

        def work(keys, texts, scripts):
            got = [_run(bpe, t or "", [(e["start_at"], e["end_at"], e["replacement"]) for e in s or []]) for t, s in zip(texts, scripts, strict=True)]
            return {id_col: keys} | {n: [g[i] for g in got] for i, n in enumerate(("n_tokens", "n_edits", "n_tokens_after", "n_reencoded", "text_after"))}

        return work

    return map_rows(joined, make, f"{id_col} long, {COUNTS}, text_after string")
