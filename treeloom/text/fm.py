"""A self-index over a collection of terminated texts: Burrows-Wheeler transform, backward search, locating, extraction.

Rows are numbered from 0 and ranges are half open.  Terminators are byte 0 and sort by text, below every other symbol, so
row t is the one of text t's terminator.
"""

from __future__ import annotations

import io

import numpy as np

from treeloom.text.rank import BLOCK, build_rank


class PatternError(ValueError):
    pass


def suffix_order(symbols: np.ndarray) -> np.ndarray:
    """Order of the suffixes of a sequence of small integers from 0, by prefix doubling.

    The first sort is by as many symbols as a machine word holds; from then on only suffixes that are not yet told apart are sorted."""
    n = len(symbols)
    code = np.cumsum(np.bincount(symbols, minlength=1) > 0, dtype=np.int64)[symbols]  # from 1; 0: past the end
    width = int(code.max(initial=1)).bit_length()
    k = 63 // width
    key = np.zeros(n, np.int64)
    for j in range(k):
        key <<= width
        key[: max(n - j, 0)] |= code[j:]
    order = np.argsort(key)
    head = np.append(True, key[order][1:] != key[order][:-1]) if n else np.zeros(0, bool)
    rank = np.empty(n, np.int64)
    # a suffix is ranked by the first place of its group
    rank[order] = np.maximum.accumulate(np.where(head, np.arange(n), 0))
    places = np.nonzero(~(head & np.append(head[1:], True)))[0]
    while len(places):
        who = order[places]
        second = np.where(who + k < n, rank[np.minimum(who + k, n - 1)] + 1, 0)
        key = rank[who] * (n + 1) + second
        by = np.argsort(key)
        who, key = who[by], key[by]
        order[places] = who
        head = np.append(True, key[1:] != key[:-1])
        rank[who] = np.maximum.accumulate(np.where(head, places, 0))
        places = places[~(head & np.append(head[1:], True))]
        k *= 2
    return order


def transform(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(last column, suffix order) of the texts with their terminators."""
    d = len(texts)
    if any(b"\0" in t for t in texts):
        raise PatternError("texts must not hold the terminator")
    raw = np.frombuffer(b"\0".join(texts) + b"\0" if d else b"", np.uint8)
    ends = raw == 0
    symbols = raw.astype(np.int64) + d
    symbols[ends] = np.arange(d)
    order = suffix_order(symbols)
    return raw[order - 1] if d else raw, order


class TextIndex:
    """``sample``: every so many text positions are kept for locating; ``kind``: layout of the rank structure."""

    def __init__(self, column: np.ndarray, doc: np.ndarray, marks: np.ndarray, samples: np.ndarray, starts: np.ndarray, sample: int, kind: str):
        self.column, self.doc, self.marks, self.samples, self.starts, self.sample, self.kind = column, doc, marks, samples, starts, sample, kind
        self.n, self.d = len(column), len(doc)
        counts = np.bincount(column, minlength=256)
        self.smaller = np.concatenate([[0], counts.cumsum()])[:256]
        self.rank = build_rank(column, kind)
        self._samples_before: np.ndarray | None = None
        self._back: np.ndarray | None = None

    @classmethod
    def build(cls, texts: list[bytes], sample: int = 64, kind: str = "blocks") -> TextIndex:
        column, order = transform(texts)
        starts = np.cumsum([0, *(len(t) + 1 for t in texts)])
        # rows whose suffix starts a text, in row order, give the texts
        doc = np.searchsorted(starts, order[column == 0]).astype(np.int64)
        marks = order % sample == 0
        return cls(column, doc, marks, order[marks], starts, sample, kind)

    @property
    def _marked(self) -> np.ndarray:
        """Samples before each row, for locating only."""
        if self._samples_before is None:
            self._samples_before = np.concatenate([[0], np.cumsum(self.marks, dtype=np.int32)], dtype=np.int32)
        return self._samples_before

    # --- storage

    def pack(self) -> bytes:
        out = io.BytesIO()
        np.savez(out, column=self.column, doc=self.doc, marks=np.packbits(self.marks), samples=self.samples.astype(np.uint32 if self.n < 1 << 32 else np.int64), starts=self.starts, sample=np.array([self.sample]), kind=np.array([self.kind]))
        return out.getvalue()

    @classmethod
    def unpack(cls, data: bytes) -> TextIndex:
        z = np.load(io.BytesIO(data))
        return cls(z["column"], z["doc"], np.unpackbits(z["marks"], count=len(z["column"])).astype(bool), z["samples"].astype(np.int64), z["starts"], int(z["sample"][0]), str(z["kind"][0]))

    def sizes(self) -> dict[str, int]:
        """Bits of each part."""
        log_n = max(1, int(max(self.n, 2) - 1).bit_length())
        return {"text": self.rank.bits(), "samples": len(self.samples) * log_n + self.n, "doc": self.d * max(1, int(max(self.d, 2) - 1).bit_length())}

    # --- search

    @staticmethod
    def symbols(pattern: str | bytes) -> bytes:
        p = pattern.encode() if isinstance(pattern, str) else pattern
        if not p or b"\0" in p:
            raise PatternError("a pattern must hold a symbol and no terminator")
        return p

    def search(self, pattern: str | bytes, start: tuple[int, int] | None = None) -> tuple[int, int]:
        """Rows whose suffix begins with the pattern (followed by what the ``start`` rows begin with)."""
        low, high = start if start is not None else (0, self.n)
        for c in reversed(self.symbols(pattern)):
            if low >= high:
                break
            r = self.rank.rank(c, np.array([low, high]))
            low, high = int(self.smaller[c] + r[0]), int(self.smaller[c] + r[1])
        return low, max(low, high)

    def back(self) -> np.ndarray:
        """``lf`` of every row: rows with one symbol keep their order, so that one stable sort of the column gives all ranks."""
        if self._back is None:
            self._back = np.empty(self.n, np.int32 if self.n < 1 << 31 else np.int64)
            self._back[np.argsort(self.column, kind="stable")] = np.arange(self.n, dtype=self._back.dtype)
        return self._back

    def lf(self, rows: np.ndarray) -> np.ndarray:
        """Rows of the suffixes that start one position earlier."""
        if self._back is not None or len(rows) * BLOCK > self.n:
            return self.back()[rows].astype(np.int64)
        out = np.empty(len(rows), np.int64)
        c = self.column[rows]
        for s in np.unique(c):
            at = c == s
            out[at] = self.smaller[s] + self.rank.rank(int(s), rows[at])
        return out

    def _texts_at(self, low: int, high: int) -> np.ndarray:
        """Texts that start at rows of a range."""
        a, b = self.rank.rank(0, np.array([low, high]))
        return self.doc[int(a) : int(b)]

    def locate(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(text, offset in it) of the suffixes of rows: back to the next sample or text start, all rows at once."""
        rows = np.asarray(rows, np.int64)
        where = np.full(len(rows), -1, np.int64)
        steps = np.zeros(len(rows), np.int64)
        here, open_ = rows.copy(), np.arange(len(rows))
        while len(open_):
            at = here[open_]
            marked = self.marks[at]
            done = open_[marked]
            where[done] = self.samples[self._marked[at[marked]]] + steps[done]
            open_ = open_[~marked]
            at = here[open_]
            first = self.column[at] == 0
            done = open_[first]
            where[done] = self.starts[self.doc[self.rank.rank(0, at[first])]] + steps[done]
            open_ = open_[~first]
            here[open_] = self.lf(here[open_])
            steps[open_] += 1
        text = np.searchsorted(self.starts, where, "right") - 1
        return text, where - self.starts[text]

    # --- predicates: ids of texts, ascending

    def global_count(self, p: str | bytes) -> int:
        low, high = self.search(p)
        return high - low

    def contains(self, p: str | bytes) -> np.ndarray:
        return np.unique(self.locate(np.arange(*self.search(p)))[0])

    def starts_with(self, p: str | bytes) -> np.ndarray:
        return np.sort(self._texts_at(*self.search(p)))

    def ends_with(self, p: str | bytes) -> np.ndarray:
        return np.unique(self.locate(np.arange(*self.search(p, (0, self.d))))[0])

    def ends_with_count(self, p: str | bytes) -> int:
        low, high = self.search(p, (0, self.d))
        return high - low

    def equals(self, p: str | bytes) -> np.ndarray:
        return np.sort(self._texts_at(*self.search(p, (0, self.d))))

    def at_most(self, p: str | bytes) -> np.ndarray:
        """Texts that are not after the pattern: the upper end starts at the terminators and moves by one rank a symbol."""
        end = self.d
        for c in reversed(self.symbols(p)):
            end = int(self.smaller[c] + self.rank.rank(c, np.array([end]))[0])
        return np.sort(self._texts_at(0, end))

    def compare(self, op: str, p: str | bytes) -> np.ndarray:
        up = self.at_most(p)
        if op in ("<", ">="):
            up = np.setdiff1d(up, self.equals(p))
        return up if op in ("<", "<=") else np.setdiff1d(np.arange(self.d), up)

    def in_range(self, ids: np.ndarray, x: int | None, y: int | None) -> np.ndarray:
        low = 0 if x is None else int(np.searchsorted(ids, x))
        return ids[low:] if y is None else ids[low : int(np.searchsorted(ids, y, "right"))]

    def extract(self, text: int) -> bytes:
        out, row = bytearray(), np.array([text])
        while (c := int(self.column[row[0]])) != 0:
            out.append(c)
            row = self.lf(row)
        return bytes(reversed(out))

    def extract_all(self) -> list[bytes]:
        """All texts: from every sample and every end of a text back to the sample before, all of them a step at a time."""
        out = np.zeros(self.n, np.uint8)
        marked = np.nonzero(self.marks)[0]
        row, at = np.concatenate([marked, np.arange(self.d)]), np.concatenate([self.samples, self.starts[1:] - 1])
        kept, back = np.zeros(self.n, bool), self.back()
        kept[self.samples] = True
        while len(row):
            c = self.column[row]
            inside = c != 0  # the symbol before the first of a text is a terminator
            row, at = row[inside], at[inside] - 1
            out[at] = c[inside]
            going = ~kept[at]  # what lies before a sample is read from there
            row, at = back[row[going]], at[going]
        whole = out.tobytes()
        return [whole[a : b - 1] for a, b in zip(self.starts.tolist(), self.starts[1:].tolist())]

    def approximate(self, p: str | bytes, k: int) -> np.ndarray:
        """Texts with a substring at most ``k`` substitutions away, by backtracking on the backward search."""
        p = self.symbols(p)
        present = [c for c in np.unique(self.column).tolist() if c]
        found: list[tuple[int, int]] = []
        stack = [(len(p), 0, self.n, k)]
        while stack:
            i, low, high, left = stack.pop()
            if i == 0:
                found.append((low, high))
                continue
            for c in present if left else [p[i - 1]]:
                r = self.rank.rank(c, np.array([low, high]))
                a, b = int(self.smaller[c] + r[0]), int(self.smaller[c] + r[1])
                if a < b:
                    stack.append((i - 1, a, b, left - (c != p[i - 1])))
        rows = np.concatenate([np.arange(a, b) for a, b in found] or [np.zeros(0, np.int64)])
        return np.unique(self.locate(rows)[0])

    def within_edits(self, p: str | bytes, k: int) -> np.ndarray:
        """Texts with a substring at most ``k`` insertions, deletions or substitutions away, by backtracking on the backward search."""
        p = self.symbols(p)
        present = [c for c in np.unique(self.column).tolist() if c]
        found: set[tuple[int, int]] = set()
        seen: set[tuple[int, int, int, int]] = set()
        stack = [(len(p), 0, self.n, k)]
        while stack:
            state = stack.pop()
            if state in seen:
                continue
            seen.add(state)
            i, low, high, left = state
            if i == 0:
                found.add((low, high))
                continue
            if left:
                stack.append((i - 1, low, high, left - 1))  # a symbol of the pattern is missing in the text
            for c in present if left else [p[i - 1]]:
                r = self.rank.rank(c, np.array([low, high]))
                a, b = int(self.smaller[c] + r[0]), int(self.smaller[c] + r[1])
                if a < b:
                    stack.append((i - 1, a, b, left - (c != p[i - 1])))
                    if left:
                        stack.append((i, a, b, left - 1))  # a symbol of the text more
        rows = np.concatenate([np.arange(a, b) for a, b in found] or [np.zeros(0, np.int64)])
        return np.unique(self.locate(np.unique(rows))[0])

    def matrix(self, weights: list[dict[int, int]], threshold: int) -> np.ndarray:
        """Rows of occurrences that score over ``threshold``: extended backwards, cut by the best that can still come."""
        best = np.cumsum([0, *(max(w.values()) for w in weights)])
        found, stack = [], [(len(weights), 0, self.n, 0)]
        while stack:
            i, low, high, score = stack.pop()
            if i == 0:
                found.append(np.arange(low, high))
                continue
            for c, w in weights[i - 1].items():
                if score + w + best[i - 1] > threshold:
                    r = self.rank.rank(c, np.array([low, high]))
                    a, b = int(self.smaller[c] + r[0]), int(self.smaller[c] + r[1])
                    if a < b:
                        stack.append((i - 1, a, b, score + w))
        return np.concatenate(found) if found else np.zeros(0, np.int64)


#: Texts that are walked one after another rather than a step at a time.
FEW_TEXTS = 32


def merge(a: TextIndex, b: TextIndex) -> TextIndex:
    """One index of the texts of ``a`` and then ``b``: the rows of b find their places in a by backward search."""
    if not a.n or not b.n:
        return b if not a.n else a
    places = np.empty(b.n, np.int64)
    back = b.back()
    row, place = np.arange(b.d), np.full(b.d, a.d)
    places[row] = place
    while True:
        c = b.column[row]
        going = c != 0
        row, place, c = row[going], place[going], c[going]
        if len(row) <= FEW_TEXTS:
            break
        place = a.smaller[c] + a.rank.ranks(c, place)
        row = back[row]
        places[row] = place
    # few texts are left, long ones: a step of one costs less than one of an array
    column, onward, smaller, one = b.column.tobytes(), memoryview(back), a.smaller.tolist(), a.rank.one
    for r, p in zip(row.tolist(), place.tolist()):
        while c := column[r]:
            p = smaller[c] + one(c, p)
            r = onward[r]
            places[r] = p
    target = places + np.arange(b.n)
    column, marks = np.empty(a.n + b.n, np.uint8), np.empty(a.n + b.n, bool)
    own = np.ones(a.n + b.n, bool)
    own[target] = False
    column[own], column[target] = a.column, b.column
    marks[own], marks[target] = a.marks, b.marks
    samples = np.full(a.n + b.n, -1, np.int64)
    both = samples.copy()
    both[np.nonzero(own)[0][a.marks]] = a.samples
    both[target[b.marks]] = b.samples + a.n
    # the first text of each index is preceded by its own last terminator
    is_start = column == 0
    doc = np.empty(a.n + b.n, np.int64)
    doc[np.nonzero(own)[0][a.column == 0]] = a.doc
    doc[target[b.column == 0]] = b.doc + a.d
    return TextIndex(column, doc[is_start], marks, both[marks], np.concatenate([a.starts, b.starts[1:] + a.n]), a.sample, a.kind)


class RangeReport:
    """Which ids of doc[low:high] lie in [x, y]: a balanced wavelet over the ids, one answer in the depth of the tree."""

    def __init__(self, doc: np.ndarray):
        self.top = max(1, int(max(len(doc), 2) - 1).bit_length())
        self.levels: list[np.ndarray] = []
        self.zeros: list[int] = []
        cur = np.asarray(doc)
        for bit in range(self.top - 1, -1, -1):
            ones = (cur >> bit) & 1
            self.levels.append(np.concatenate([[0], np.cumsum(ones)]))
            self.zeros.append(int((ones == 0).sum()))
            cur = np.concatenate([cur[ones == 0], cur[ones == 1]])

    def report(self, low: int, high: int, x: int, y: int) -> list[int]:
        out, stack = [], [(0, low, high, 0)]
        while stack:
            level, a, b, prefix = stack.pop()
            width = self.top - level
            if a >= b or prefix + (1 << width) - 1 < x or prefix > y:
                continue
            if level == self.top:
                out += [prefix] * (b - a)
                continue
            ones = self.levels[level]
            i, j = int(ones[a]), int(ones[b])
            stack.append((level + 1, a - i, b - j, prefix))
            stack.append((level + 1, self.zeros[level] + i, self.zeros[level] + j, prefix + (1 << (width - 1))))
        return sorted(out)
