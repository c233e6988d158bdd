"""Byte-level BPE by prefix dynamic programming.

For every byte prefix of a pre-token exactly one token can be the last one of that prefix's encoding. Keeping that
token for each prefix makes an encoding a walk back over the table, an append a continuation of the table and an
edit a short recomputation that stops where the old states are met again.

Edge cases: null text is the empty text, which has no tokens; texts of any length are encoded whole; repeated rows
give repeated results; extra columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
from functools import lru_cache

import ahocorasick
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows

#: Distinct pre-tokens that a Python worker remembers; the memory is emptied when full.
MEMO = 400_000


class ByteBpe:
    """Encoder and decoder for a rank file. ``ranks`` maps token bytes to ids, lower ids merge first."""

    def __init__(self, ranks: dict[bytes, int], pattern: str) -> None:
        self.ranks = ranks
        self.find = regex.compile(pattern).findall
        self.matches = regex.compile(pattern).finditer
        self.of_id = {i: b for b, i in ranks.items()}
        self.halves: dict[int, tuple[int, int]] = {}
        self.words = ahocorasick.Automaton(ahocorasick.STORE_INTS)
        self.sizes: dict[int, int] = {}
        self.longest = 1
        monotone = True
        for token, rank in sorted(ranks.items(), key=lambda x: len(x[0])):
            parts, last = self._merge(token)
            if len(parts) > 1:  # no sequence of merges makes it, so it only stands for a whole pre-token
                continue
            if last:
                self.halves[rank] = last
                monotone &= max(last) < rank
            self.words.add_word(token.decode("latin-1"), rank)
            self.sizes[rank] = len(token)
            self.longest = max(self.longest, len(token))
        self.words.make_automaton()
        self._fits = self._fits_by_spines if monotone else self._fits_by_merging
        self.known: dict[int, bool] = {}
        self.spines: dict[tuple[int, int], list[int]] = {}
        self.memo: dict[str, tuple] = {}
        self.counted: dict[str, int] = {}

    def _merge(self, data: bytes, wall: int = -1) -> tuple[list[bytes], tuple[int, int] | None]:
        """Merge by lowest rank, leftmost first; the parts, and the ids that the last merge joined. A merge over the byte
        offset ``wall`` ends the work and gives no parts."""
        parts, last = [data[i : i + 1] for i in range(len(data))], None
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                r = self.ranks.get(parts[i] + parts[i + 1])
                if r is not None and (best is None or r < best):
                    best, at = r, i
            if best is None:
                break
            if wall >= 0 and sum(map(len, parts[: at + 1])) == wall:
                return [], None
            last = (self.ranks[parts[at]], self.ranks[parts[at + 1]])
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts, last

    def _fits_by_merging(self, a: int, b: int) -> bool:
        left = self.of_id[a]
        return bool(self._merge(left + self.of_id[b], len(left))[0])

    def _spine(self, token: int, side: int) -> list[int]:
        """From the outermost byte up to the token itself, along its left (0) or right (1) edge."""
        got = self.spines.get((token, side))
        if got is None:
            got = [token]
            while got[-1] in self.halves:
                got.append(self.halves[got[-1]][side])
            got.reverse()
            self.spines[token, side] = got
        return got

    def _fits_by_spines(self, a: int, b: int) -> bool:
        """May b follow a? Both edges grow in the order of ranks; no merge over the border may come first."""
        up, down, of, ranks = self._spine(a, 1), self._spine(b, 0), self.of_id, self.ranks
        i = j = 0
        never = 1 << 60
        while True:
            cross = ranks.get(of[up[i]] + of[down[j]], never)
            left = up[i + 1] if i + 1 < len(up) else never
            right = down[j + 1] if j + 1 < len(down) else never
            if cross < left and cross <= right:
                return False
            if left == right == never:
                return True
            if left <= right:
                i += 1
            else:
                j += 1

    def _extend(self, data: str, last: list[int], start: int, until=None) -> None:
        """Fill last[e] for the prefixes that end after ``start``; ``until(e)`` may stop the walk early."""
        lead = max(0, start - self.longest)
        sizes, known = self.sizes, self.known
        done = start
        for end, token in self.words.iter(data, lead):
            end += 1
            if end <= start or last[end] >= 0:
                continue
            begin = end - sizes[token]
            if begin < lead:
                continue
            if begin:
                before = last[begin]
                key = before << 24 | token
                ok = known.get(key)
                if ok is None:
                    ok = known[key] = self._fits(before, token)
                if not ok:
                    continue
            last[end] = token
            if until and end > done and until(end):
                return
            done = end

    def piece(self, data: bytes) -> list[int]:
        """Ids of one pre-token."""
        whole = self.ranks.get(data)
        if whole is not None:
            return [whole]
        last = [0] + [-1] * len(data)
        self._extend(data.decode("latin-1"), last, 0)
        return self._walk(last)

    def _walk(self, last: list[int]) -> list[int]:
        out, end = [], len(last) - 1
        while end:
            out.append(last[end])
            end -= self.sizes[last[end]]
        out.reverse()
        return out

    def remembered(self, piece: str) -> tuple[int, str, bytes]:
        """Count of ids, ids as decimal text and the bytes that these ids decode to, of one pre-token."""
        got = self.memo.get(piece)
        if got is None:
            if len(self.memo) >= MEMO:
                self.memo.clear()
            if len(self.known) >= 4 * MEMO:
                self.known.clear()
            ids = self.piece(piece.encode())
            got = self.memo[piece] = (len(ids), ",".join(map(str, ids)), self.decode(ids))
        return got

    def counts(self, pieces: list[str]) -> list[int]:
        """Count of ids of each pre-token."""
        if len(self.counted) >= 2 * MEMO:
            self.counted.clear()
        if len(self.known) >= 4 * MEMO:
            self.known.clear()
        get, out = self.counted.get, []
        for p in pieces:
            n = get(p)
            if n is None:
                n = self.counted[p] = len(self.piece(p.encode()))
            out.append(n)
        return out

    def encode(self, text: str | None) -> list[int]:
        return [i for p in self.find(text or "") for i in self.piece(p.encode())]

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.of_id.__getitem__, ids))


class PrefixTable:
    """The table of one pre-token, kept so that appends and edits stay exact without a new start."""

    def __init__(self, bpe: ByteBpe, data: bytes = b"") -> None:
        self.bpe, self.data, self.last, self.work = bpe, "", [0], 0
        self.append(data)

    def append(self, more: bytes) -> None:
        start = len(self.data)
        self.data += more.decode("latin-1")
        self.last += [-1] * len(more)
        if more:
            self.bpe._extend(self.data, self.last, start)
        self.work += len(more)

    def replace(self, start: int, end: int, new: bytes) -> None:
        """Put ``new`` in place of bytes start..end; prefixes behind the edit are taken over once a whole token's reach agrees."""
        old, shift = self.last, len(new) - (end - start)
        self.data = self.data[:start] + new.decode("latin-1") + self.data[end:]
        self.last = old[: start + 1] + [-1] * (len(self.data) - start)
        same, reach, stop = 0, self.bpe.longest, 0

        def met(e: int) -> bool:
            nonlocal same, stop
            same = same + 1 if e > start + len(new) and old[e - shift] == self.last[e] else 0
            stop = e
            return same > reach

        self.bpe._extend(self.data, self.last, start, met)
        self.work += stop - start
        if same > reach:
            self.last[stop:] = old[stop - shift :]

    def ids(self) -> list[int]:
        whole = self.bpe.ranks.get(self.data.encode("latin-1"))
        return [whole] if whole is not None else self.bpe._walk(self.last)


@lru_cache(maxsize=2)
def from_file(path: str, pattern: str) -> ByteBpe:
    with open(path, "rb") as lines:
        return ByteBpe({base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}, pattern)


def encode(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Ids of every text and the text they decode to: id, ids array<int>, decoded string."""

    def make():
        bpe = from_file(path, pattern)

        def work(keys, texts):
            ids = [bpe.encode(t) for t in texts]
            return {id_col: keys, "ids": ids, "decoded": [bpe.decode(x).decode() for x in ids]}

        return work

    return map_rows(docs.select(F.col(id_col).cast("long").alias(id_col), F.col(text_col).cast("string").alias(text_col)), make, f"{id_col} long, ids array<int>, decoded string")


def digests(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Counts and digests of the same encoding and decoding, without moving the ids: id, n_tokens, ids_sha256, decoded_sha256."""

    def make():
        bpe = from_file(path, pattern)

        def work(keys, texts):
            counts, ids, decoded = [], [], []
            for text in texts:
                got = [*map(bpe.remembered, bpe.find(text or ""))]
                counts.append(sum(x[0] for x in got))
                ids.append(hashlib.sha256(",".join([x[1] for x in got]).encode()).hexdigest())
                decoded.append(hashlib.sha256(b"".join([x[2] for x in got])).hexdigest())
            return {id_col: keys, "n_tokens": counts, "ids_sha256": ids, "decoded_sha256": decoded}

        return work

    return map_rows(docs.select(F.col(id_col).cast("long").alias(id_col), F.col(text_col).cast("string").alias(text_col)), make, f"{id_col} long, n_tokens long, ids_sha256 string, decoded_sha256 string")
