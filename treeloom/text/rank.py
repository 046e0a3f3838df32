"""Rank and select over a symbol sequence, in four layouts with one interface.

``blocks``: counts at every 128th position and a count inside the block (default); ``wavelet``: bit planes of balanced
codes; ``huffman``: bit planes of Huffman codes; ``runs``: run heads with cumulative lengths.  ``rank(c, i)`` counts the
symbol c among the first i positions and takes arrays; ``select(c, j)`` is the position of the j-th c, from 1.
"""

from __future__ import annotations

import heapq

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BLOCK = 128


class _Ranks:
    """Ranks of arrays of symbols at once, and of one symbol at one place."""

    def ranks(self, c: np.ndarray, i: np.ndarray) -> np.ndarray:
        out = np.empty(len(c), np.int64)
        for s in np.unique(c):
            at = c == s
            out[at] = self.rank(int(s), i[at])
        return out

    def one(self, c: int, i: int) -> int:
        return int(self.rank(c, np.array(i)))


class Blocks(_Ranks):
    """The counts of a symbol are taken when it is first asked for: a search asks for those of its pattern only."""

    def __init__(self, seq: np.ndarray):
        self.seq, self.n = seq, len(seq)
        self.symbols = np.nonzero(np.bincount(seq, minlength=256))[0]
        self.row = np.full(256, -1)
        self.row[self.symbols] = np.arange(len(self.symbols))
        self.blocks = self.n // BLOCK + 1
        self._own: dict[int, np.ndarray] = {}
        self._all: np.ndarray | None = None
        self._inside = np.arange(BLOCK)
        self._bytes: bytes | None = None

    def _before(self, c: int) -> np.ndarray:
        """Occurrences of one symbol before each block."""
        if self._all is not None:
            return self._all[self.row[c]]
        got = self._own.get(c)
        if got is None:
            hit = self.seq == c
            whole = self.n // BLOCK * BLOCK
            counts = np.count_nonzero(hit[:whole].reshape(-1, BLOCK), axis=1)
            got = self._own[c] = np.concatenate([[0], counts.cumsum()]).astype(np.uint32)
        return got

    @property
    def before(self) -> np.ndarray:
        """The same of all symbols, one row each."""
        if self._all is None:
            ids = self.row[self.seq] * self.blocks + np.arange(self.n) // BLOCK
            counts = np.bincount(ids, minlength=len(self.symbols) * self.blocks).reshape(len(self.symbols), self.blocks)
            self._all = np.concatenate([np.zeros((len(self.symbols), 1), np.int64), counts.cumsum(axis=1)], axis=1)[:, :-1].astype(np.uint32)
        return self._all

    def rank(self, c: int, i: np.ndarray) -> np.ndarray:
        i = np.asarray(i)
        if self.row[c] < 0:
            return np.zeros(i.shape, np.int64)
        b = i // BLOCK
        at = b[..., None] * BLOCK + self._inside
        hit = (self.seq[np.minimum(at, self.n - 1)] == c) & (at < i[..., None])
        return self._before(c)[b].astype(np.int64) + hit.sum(axis=-1)

    def ranks(self, c: np.ndarray, i: np.ndarray) -> np.ndarray:
        b = i // BLOCK
        at = b[:, None] * BLOCK + self._inside
        hit = (self.seq[np.minimum(at, self.n - 1)] == c[:, None]) & (at < i[:, None])
        return np.where(self.row[c] < 0, 0, self.before[self.row[c], b].astype(np.int64) + hit.sum(axis=1))

    def one(self, c: int, i: int) -> int:
        if self._bytes is None:
            self._bytes, self._counts, self._row = self.seq.tobytes(), memoryview(self.before), self.row.tolist()
        k = self._row[c]
        return self._counts[k, i // BLOCK] + self._bytes.count(c, i // BLOCK * BLOCK, i) if k >= 0 else 0

    def select(self, c: int, j: int) -> int:
        before = self._before(c)
        b = int(np.searchsorted(before, j)) - 1
        inside = np.nonzero(self.seq[b * BLOCK : (b + 1) * BLOCK] == c)[0]
        return b * BLOCK + int(inside[j - 1 - int(before[b])])

    def bits(self) -> int:
        return 8 * (self.seq.nbytes + 4 * len(self.symbols) * self.blocks)


class _Bits:
    """A plain bitmap with a count at every 64th bit."""

    def __init__(self, bits: np.ndarray):
        self.n = len(bits)
        padded = np.zeros((self.n // 64 + 1) * 64, np.uint8)
        padded[: self.n] = bits
        self.words = np.packbits(padded, bitorder="little").view(np.uint64)
        self.before = np.concatenate([[0], np.cumsum(np.bitwise_count(self.words), dtype=np.int64)])[:-1].astype(np.uint32)

    def ones(self, i: np.ndarray) -> np.ndarray:
        w = i >> 6
        mask = (np.uint64(1) << (i & 63).astype(np.uint64)) - np.uint64(1)
        return self.before[w].astype(np.int64) + np.bitwise_count(self.words[w] & mask)

    def bits(self) -> int:
        return 8 * (self.words.nbytes + self.before.nbytes)


def huffman_codes(counts: dict[int, int]) -> dict[int, str]:
    heap = [(n, k, (c,)) for k, (c, n) in enumerate(sorted(counts.items()))]
    codes = {c: "" for c in counts}
    if len(heap) == 1:
        return {heap[0][2][0]: "0"}
    heapq.heapify(heap)
    fresh = len(heap)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        for bit, part in (("0", a), ("1", b)):
            for c in part[2]:
                codes[c] = bit + codes[c]
        heapq.heappush(heap, (a[0] + b[0], fresh, a[2] + b[2]))
        fresh += 1
    return codes


class Wavelet(_Ranks):
    """Bit planes of a prefix code, one node for each proper prefix."""

    def __init__(self, seq: np.ndarray, shape: str = "wavelet"):
        self.n = len(seq)
        values, counts = np.unique(seq, return_counts=True)
        width = max(1, int(len(values) - 1).bit_length())
        found = dict(zip(values.tolist(), counts.tolist()))
        self.codes = huffman_codes(found) if shape == "huffman" else {c: format(k, f"0{width}b") for k, c in enumerate(found)}
        self.nodes: dict[str, _Bits] = {}
        todo = [("", seq)]
        while todo:
            prefix, part = todo.pop()
            below = {c: code for c, code in self.codes.items() if code.startswith(prefix) and len(code) > len(prefix)}
            if not below or not len(part):
                continue
            ones = np.zeros(256, np.uint8)
            ones[[c for c, code in below.items() if code[len(prefix)] == "1"]] = 1
            bits = ones[part]
            self.nodes[prefix] = _Bits(bits)
            todo += [(prefix + "0", part[bits == 0]), (prefix + "1", part[bits == 1])]

    def rank(self, c: int, i: np.ndarray) -> np.ndarray:
        i = np.asarray(i, np.int64)
        code = self.codes.get(int(c))
        if code is None:
            return np.zeros(i.shape, np.int64)
        for k, bit in enumerate(code):
            ones = self.nodes[code[:k]].ones(i)
            i = ones if bit == "1" else i - ones
        return i

    def select(self, c: int, j: int) -> int:
        low, high = 0, self.n
        while low < high:
            mid = (low + high) // 2
            low, high = (mid + 1, high) if int(self.rank(c, np.array(mid + 1))) < j else (low, mid)
        return low

    def bits(self) -> int:
        return sum(b.bits() for b in self.nodes.values())


class Runs(_Ranks):
    def __init__(self, seq: np.ndarray):
        self.n = len(seq)
        self.heads = np.nonzero(np.append(True, seq[1:] != seq[:-1]))[0] if self.n else np.zeros(0, np.int64)
        lengths = np.diff(np.append(self.heads, self.n))
        self.symbol = seq[self.heads]
        self.starts: dict[int, np.ndarray] = {}
        self.before: dict[int, np.ndarray] = {}
        for c in np.unique(self.symbol).tolist():
            at = self.symbol == c
            self.starts[c], self.before[c] = self.heads[at], np.append(0, lengths[at].cumsum())

    def rank(self, c: int, i: np.ndarray) -> np.ndarray:
        i = np.asarray(i)
        if c not in self.starts:
            return np.zeros(i.shape, np.int64)
        starts, before = self.starts[c], self.before[c]
        j = np.searchsorted(starts, i, "left")
        k = np.maximum(j - 1, 0)
        inside = np.minimum(i - starts[k], before[k + 1] - before[k])
        return np.where(j > 0, before[k] + inside, 0)

    select = Wavelet.select

    def bits(self) -> int:
        return 8 * (self.heads.nbytes + self.symbol.nbytes + sum(b.nbytes for b in self.before.values()))


def build_rank(seq: np.ndarray, kind: str = "blocks") -> Blocks | Wavelet | Runs:
    if kind == "blocks":
        return Blocks(seq)
    if kind == "runs":
        return Runs(seq)
    return Wavelet(seq, kind)


def rank_frame(df: DataFrame, group: list[str], order: str, symbol: str) -> DataFrame:
    """The relational form: ``rank`` of each row's symbol up to and with it; the row itself is select of that number."""
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(*group, symbol).orderBy(order)).cast("long"))
