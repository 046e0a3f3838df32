"""Removal of byte strings that repeat, by a hash-compared suffix sort of sampled suffixes.

A byte goes if some ``length``-byte string that covers it also starts anywhere else.  Two equal strings have the same
least ``GRAM``-byte gram at the same place, so it is enough to compare suffixes at those least grams (anchors).  Every
window of ``length`` bytes belongs to the leftmost least gram in it; the windows of one anchor are consecutive and make up
its context.

1. Each text yields its anchors with a hash of the gram and one of the whole context, both from its bytes.
2. Contexts that occur twice or more are repeated throughout.  They are counted by gram and a 128-bit digest, with map-side
   sums, so the copies of a text never meet in one task; joins with the counts treat frequent keys apart.
3. Of anchors whose gram has several contexts, one occurrence of each context is fetched with its bytes.  Within a task
   the contexts of each gram are sorted twice, by what follows the anchor and by what precedes it, reversed, with a
   mergesort that compares suffixes by their longest common extension, found by binary search on prefix polynomial
   hashes.  Neighbours' extensions are verified byte by byte; if a collision shows, the task sorts by bytes.  A window
   repeats if another context shares the order class of both of its sides.
4. Grams with more than ``SORT_LIMIT`` contexts are split: windows that start 1 to 43 bytes apart share a core, and
   contexts are grouped by that instead; equal stretches collapse to one.  Cores with too many different
   stretches are split again, down to single windows, which need counting only.  So every group that is sorted is bounded.

Null and shorter texts lose nothing.  Repeated rows repeat each other's bytes.  Rows are told apart by 128 bits of doc_id and
text (``row``, ``row2``), so that null and repeated ids are fine.  An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treeloom.llm.store import discard, keyed_join, row_identity, saved

GRAM = 32
CHUNK = 1 << 20
SORT_LIMIT = 256
_MULTIPLIER = 0x9E3779B97F4A7C15
_INVERSE = pow(_MULTIPLIER, -1, 1 << 64)


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


_BYTE_VALUES = np.frombuffer(b"".join(xxhash.xxh3_64_digest(bytes([b]), seed=7) for b in range(256)), np.uint64)


class PrefixHash:
    """Polynomial hashes modulo 2^64 of all substrings of a buffer, from one prefix sum."""

    def __init__(self, data: np.ndarray):
        n = len(data)
        self.sums = np.zeros(n + 1, np.uint64)
        np.cumsum(_BYTE_VALUES[data] * _powers(_MULTIPLIER, n), dtype=np.uint64, out=self.sums[1:])
        self.undo = _powers(_INVERSE, n + 1)

    def __call__(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return (self.sums[end] - self.sums[start]) * self.undo[start]


def _spread(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xFF51AFD7ED558CCD)
    return h ^ (h >> np.uint64(32))


def anchors(data: np.ndarray, bounds: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """Of texts concatenated in ``data`` (text i is bounds[i] to bounds[i + 1]): text, first window, last window, anchor
    position and gram hash of each anchor; positions are in ``data``, of at most ``CHUNK`` bytes."""
    starts, ends = bounds[:-1], bounds[1:]
    grams = length - GRAM + 1
    n = len(data) - GRAM + 1
    at = np.arange(n)
    h = _spread(PrefixHash(data)(at, at + GRAM))
    low = np.uint64(CHUNK - 1)
    least = (h & ~low) | at.astype(np.uint64)
    width = 1
    while width * 2 <= grams:
        least = np.minimum(least[:-width], least[width:])
        width *= 2
    if width < grams:
        shift = grams - width
        least = np.minimum(least[:-shift], least[shift:])
    text = np.repeat(np.arange(len(starts)), np.maximum(ends - starts - length + 1, 0))
    first = np.concatenate([np.arange(s, e - length + 1) for s, e in zip(starts, ends) if e - s >= length] or [np.zeros(0, np.int64)])
    where = (least[first] & low).astype(np.int64)
    new = np.ones(len(first), bool)
    new[1:] = (where[1:] != where[:-1]) | (text[1:] != text[:-1])
    head = np.nonzero(new)[0]
    tail = np.append(head[1:], len(first)) - 1
    return text[head], first[head], first[tail], where[head], h[where[head]]


def _pieces(texts: list[bytes], length: int) -> Iterator[list[tuple[int, int, bytes]]]:
    """(text, offset, bytes) in lists of at most ``CHUNK`` bytes; longer texts overlap by length - 1 bytes."""
    held, size = [], 0
    for i, t in enumerate(texts):
        if len(t) < length:
            continue
        step = CHUNK - length + 1
        for off in range(0, len(t) - length + 1, step):
            piece = t[off : off + CHUNK] if len(t) > CHUNK else t
            if size + len(piece) > CHUNK and held:
                yield held
                held, size = [], 0
            held.append((i, off, piece))
            size += len(piece)
    if held:
        yield held


def _encode(column: pa.Array) -> list[bytes]:
    return [b if b is not None else b"" for b in column.cast(pa.binary()).to_pylist()]


def anchor_rows(docs: DataFrame, length: int) -> DataFrame:
    """row, row2, start and span of each anchor's context, the anchor's place in it, gram and context digest (ctx, ctx2)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, rows2, texts = batch.column("row").to_numpy(), batch.column("row2").to_numpy(), _encode(batch.column("text"))
            for pieces in _pieces(texts, length):
                joined = b"".join(p[2] for p in pieces)
                bounds = np.cumsum([0, *(len(p[2]) for p in pieces)])
                text, p1, p2, pos, gram = anchors(np.frombuffer(joined, np.uint8), bounds, length)
                view, digest = memoryview(joined), xxhash.xxh3_128_digest
                place = pos - p1
                ctx = np.frombuffer(b"".join([digest(view[a:b], s) for a, b, s in zip(p1.tolist(), (p2 + length).tolist(), place.tolist())]), np.int64).reshape(-1, 2)
                own = np.array([p[0] for p in pieces])[text]
                offset = np.array([p[1] for p in pieces])[text] - bounds[:-1][text]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(rows[own]), pa.array(rows2[own]), pa.array((p1 + offset).astype(np.int32)), pa.array((p2 - p1 + length).astype(np.int16)), pa.array(place.astype(np.int16)), pa.array(gram.view(np.int64)), pa.array(ctx[:, 0].copy()), pa.array(ctx[:, 1].copy())],
                    ["row", "row2", "start", "span", "place", "gram", "ctx", "ctx2"],
                )

    return docs.select("row", "row2", "text").mapInArrow(run, "row long, row2 long, start int, span short, place short, gram long, ctx long, ctx2 long")


class Suffixes:
    """Suffixes of one buffer, each with a length limit, compared by hashed common extensions."""

    def __init__(self, data: np.ndarray, start: np.ndarray, size: np.ndarray):
        self.data, self.start, self.size = data, start, size
        self.hash = PrefixHash(data)

    def extension(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Longest common extension of suffixes x and y."""
        a, b = self.start[x], self.start[y]
        most = np.minimum(self.size[x], self.size[y])
        low, high = np.zeros(len(x), np.int64), most.copy()
        for _ in range(int(most.max(initial=0)).bit_length()):
            mid = (low + high + 1) >> 1
            same = self.hash(a, a + mid) == self.hash(b, b + mid)
            low, high = np.where(same, mid, low), np.where(same, high, mid - 1)
        return low

    def before(self, x: np.ndarray, y: np.ndarray, or_equal: bool) -> np.ndarray:
        e = self.extension(x, y)
        xs, ys = self.size[x], self.size[y]
        inside = (e < xs) & (e < ys)
        last = len(self.data) - 1
        bx, by = self.data[np.minimum(self.start[x] + e, last)], self.data[np.minimum(self.start[y] + e, last)]
        return np.where(inside, bx < by, (xs <= ys) if or_equal else (xs < ys))

    def sort(self, group: np.ndarray) -> np.ndarray:
        """Suffix numbers in the order of (group, suffix): all merges of one width at once."""
        order = np.argsort(group, kind="stable")
        g = group[order]
        head = np.nonzero(np.append(True, g[1:] != g[:-1]))[0]
        sizes = np.diff(np.append(head, len(g)))
        seg_start, seg_end = np.repeat(head, sizes), np.repeat(head + sizes, sizes)
        t = np.arange(len(g)) - seg_start
        width = 1
        while width < sizes.max(initial=1):
            todo = np.nonzero(seg_end - seg_start > width)[0]
            pair = t[todo] // (2 * width) * (2 * width)
            left = t[todo] % (2 * width) < width
            base = seg_start[todo] + pair
            lo = np.minimum(base + np.where(left, width, 0), seg_end[todo])
            hi = np.minimum(lo + width, seg_end[todo])
            other = lo.copy()
            me = order[todo]
            while True:
                open_ = np.nonzero(lo < hi)[0]
                if not len(open_):
                    break
                mid = (lo[open_] + hi[open_]) >> 1
                it, own, is_left = order[mid], me[open_], left[open_]
                # of equal suffixes the left run's come first
                goes = np.where(is_left, self.before(it, own, False), self.before(it, own, True))
                lo[open_], hi[open_] = np.where(goes, mid + 1, lo[open_]), np.where(goes, hi[open_], mid)
            merged = order.copy()
            merged[base + t[todo] % width + (lo - other)] = me
            order = merged
            width *= 2
        return order

    def verified(self, order: np.ndarray, shared: np.ndarray) -> bool:
        """Whether neighbours in ``order`` agree byte by byte as far as ``shared`` says."""
        x, y, n = order[:-1], order[1:], shared[1:]
        rows = np.repeat(np.arange(len(n)), n)
        k = np.arange(len(rows)) - np.repeat(np.cumsum(n) - n, n)
        return bool((self.data[self.start[x][rows] + k] == self.data[self.start[y][rows] + k]).all())


def _sorted_with_shared(data: np.ndarray, start: np.ndarray, size: np.ndarray, group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of the suffixes and how much each shares with the one before it (0 at the head of a group)."""
    s = Suffixes(data, start, size)
    order = s.sort(group)
    shared = np.zeros(len(order), np.int64)
    same = np.nonzero(group[order[1:]] == group[order[:-1]])[0]
    shared[same + 1] = s.extension(order[same], order[same + 1])
    if not s.verified(order, shared):  # a collision: compare the bytes themselves
        raw = [bytes(data[a : a + n]) for a, n in zip(start, size)]
        order = np.array(sorted(range(len(raw)), key=lambda i: (group[i], raw[i])))
        shared[:] = 0
        for j in range(1, len(order)):
            x, y = raw[order[j - 1]], raw[order[j]]
            if group[order[j]] == group[order[j - 1]]:
                shared[j] = next((i for i, (p, q) in enumerate(zip(x, y)) if p != q), min(len(x), len(y)))
    return order, shared


def repeated_windows(contexts: list[bytes], place: np.ndarray, group: np.ndarray, length: int) -> Iterator[tuple[np.ndarray, int]]:
    """(numbers of contexts, x): their window that starts x bytes before the anchor also lies in another context of the group."""
    m = len(contexts)
    data = np.frombuffer(b"".join(contexts), np.uint8)
    size = np.fromiter(map(len, contexts), np.int64, m)
    start = np.cumsum(size) - size
    right, right_shared = _sorted_with_shared(data, start + place, size - place, group)
    back = data[::-1].copy()
    left, left_shared = _sorted_with_shared(back, len(data) - (start + place), place, group)
    for x in range(int(place.max(initial=0)) + 1):
        fits = (place >= x) & (size - place >= length - x)
        if fits.sum() < 2:
            continue
        r, q = np.empty(m, np.int64), np.empty(m, np.int64)
        r[right] = np.cumsum(right_shared < length - x)
        q[left] = np.cumsum((left_shared < x) | (np.append(-1, group[left[:-1]]) != group[left]))
        rows = np.nonzero(fits)[0]
        _, where, count = np.unique(r[rows] * (m + 1) + q[rows], return_inverse=True, return_counts=True)
        rows = rows[count[where] > 1]
        if len(rows):
            yield rows, x


def _sorted_spans(contexts: DataFrame, length: int) -> DataFrame:
    """(row, row2, start, stop) of repeated stretches in contexts (gram, row, row2, start, place, single, bytes) that share a gram."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None

        def work(t: pa.Table) -> pa.RecordBatch:
            place = t.column("place").to_numpy().astype(np.int64)
            row, row2, begin = t.column("row").to_numpy(), t.column("row2").to_numpy(), t.column("start").to_numpy().astype(np.int64)
            single = t.column("single").to_numpy()
            out: list[tuple[np.ndarray, np.ndarray]] = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
            for rows, x in repeated_windows(t.column("bytes").to_pylist(), place, t.column("gram").to_numpy(), length):
                rows = rows[single[rows]]
                out.append((rows, begin[rows] + place[rows] - x))
            who, at = (np.concatenate(z) for z in zip(*out))
            # consecutive windows of a context make one span
            order = np.lexsort((at, who))
            who, at = who[order], at[order]
            new = np.append(True, (who[1:] != who[:-1]) | (at[1:] != at[:-1] + 1)) if len(who) else np.zeros(0, bool)
            head = np.nonzero(new)[0]
            tail = np.append(head[1:], len(who))[: len(head)] - 1
            return pa.RecordBatch.from_arrays([pa.array(row[who[head]]), pa.array(row2[who[head]]), pa.array(at[head].astype(np.int32)), pa.array((at[tail] + length).astype(np.int32))], ["row", "row2", "start", "stop"])

        for batch in batches:
            t = pa.Table.from_batches([batch]) if held is None else pa.concat_tables([held, pa.Table.from_batches([batch])])
            if not t.num_rows:
                continue
            gram = t.column("gram").to_numpy()
            cut = int(np.argmax(gram == gram[-1]))  # rows come in the order of their gram
            if cut:
                yield work(t.slice(0, cut))
            held = t.slice(cut)
        if held is not None and held.num_rows:
            yield work(held)

    return contexts.select("gram", "row", "row2", "start", "place", "single", "bytes").mapInArrow(run, "row long, row2 long, start int, stop int")


#: Window starts of one slice, level by level.
SLICES = (43, 11, 3, 1)


def _sliced(contexts: DataFrame, length: int, width: int) -> DataFrame:
    """The stretches of contexts (gram, row, row2, start, place, anchor, single, bytes) that hold windows of one slice, keyed by the
    bytes that all windows of the slice share."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        digest, whole = xxhash.xxh3_64_intdigest, xxhash.xxh3_128_digest
        for batch in batches:
            out = []
            for row, row2, start, anchor, single, data in zip(*(batch.column(c).to_pylist() for c in ("row", "row2", "start", "anchor", "single", "bytes"))):
                i = anchor - start
                last = len(data) - length
                # x: how far a window starts before the anchor; this context has the windows i - last to i
                for s in range(max(0, i - last) // width, i // width + 1):
                    low, high = s * width, (s + 1) * width - 1
                    a, b = max(0, i - high), min(last, i - low)
                    core = data[max(0, i - low) : i - high + length]
                    place = i - low - a
                    piece = data[a : b + length]
                    out.append((digest(core, s) - 2**63, whole(piece, place & 0xFFFF), row, row2, start + a, place, anchor, single, piece))
            cols = list(zip(*out)) if out else [[]] * 9
            kinds = (pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.int32(), pa.int16(), pa.int32(), pa.bool_(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], ["gram", "piece", "row", "row2", "start", "place", "anchor", "single", "bytes"])

    return contexts.select("row", "row2", "start", "anchor", "single", "bytes").mapInArrow(run, "gram long, piece binary, row long, row2 long, start int, place short, anchor int, single boolean, bytes binary")


def _spans(contexts: DataFrame, length: int) -> DataFrame:
    """(row, row2, start, stop) of repeated stretches of contexts (gram, kinds, row, row2, start, place, anchor, single, bytes)."""
    found = [_sorted_spans(contexts.filter(F.col("kinds") <= SORT_LIMIT).repartition("gram").sortWithinPartitions("gram"), length)]
    many = contexts.filter(F.col("kinds") > SORT_LIMIT)
    for width in SLICES:
        pieces = saved(_sliced(many, length, width), "pieces", few_files=True)
        if pieces.isEmpty():
            break
        one = F.min(F.struct("row", "row2", "start", "place", "anchor", "single", "bytes")).alias("one")
        kinds = saved(pieces.groupBy("gram", "piece").agg(F.count("*").alias("n"), one), "piece-kinds", few_files=True)
        hit = keyed_join(pieces.filter("single"), kinds.filter("n > 1").select("gram", "piece", "n"), ["gram", "piece"], "n", pieces.count(), "left_semi")
        found.append(hit.select("row", "row2", "start", (F.col("start") + F.octet_length("bytes")).alias("stop")))
        grams = saved(kinds.groupBy("gram").agg(F.count("*").alias("kinds")).filter("kinds > 1").withColumn("n", F.col("kinds")), "grams", few_files=True)
        one = keyed_join(kinds.select("gram", "one", F.col("n").alias("seen")), grams, ["gram"], "n", kinds.count())
        one = one.select("gram", "kinds", "one.row", "one.row2", "one.start", "one.place", "one.anchor", (F.col("one.single") & (F.col("seen") == 1)).alias("single"), "one.bytes")
        found.append(_sorted_spans(one.filter(F.col("kinds") <= SORT_LIMIT).repartition("gram").sortWithinPartitions("gram"), length))
        many = one.filter(F.col("kinds") > SORT_LIMIT)
    return reduce(DataFrame.unionAll, found)


def repeated_spans(docs: DataFrame, length: int = 200) -> DataFrame:
    """(row, row2, start, stop) of byte stretches of ``docs(row, row2, text)`` to remove; they may overlap."""
    every = saved(anchor_rows(docs, length), "anchors")
    # most grams occur once and are done with here
    again = saved(every.groupBy("gram").agg(F.count("*").alias("n")).filter("n > 1"), "grams", few_files=True)
    found = saved(keyed_join(every, again, ["gram"], "n", every.count(), "left_semi"), "repeated-anchors", few_files=True)
    discard(every, again)
    kinds = found.groupBy("gram", "ctx", "ctx2").agg(F.count("*").alias("n"), F.min(F.struct("row", "row2", "start", "span", "place")).alias("one"))
    kinds = saved(kinds, "contexts", few_files=True)
    grams = saved(kinds.groupBy("gram").agg(F.count("*").alias("kinds")).filter("kinds > 1").withColumn("n", F.col("kinds")), "grams", few_files=True)
    wanted = keyed_join(kinds.select("gram", (F.col("n") == 1).alias("single"), "one"), grams, ["gram"], "n", kinds.count()).select("gram", "kinds", "single", "one.*")
    per_row = wanted.groupBy("row", "row2").agg(F.collect_list(F.struct("gram", "kinds", "single", "start", "span", "place")).alias("w"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, lists = _encode(batch.column("text")), batch.column("w")
            flat = pa.RecordBatch.from_struct_array(lists.flatten())
            owner = np.repeat(np.arange(batch.num_rows), np.asarray(lists.value_lengths()))
            start, span = flat.column("start").to_pylist(), flat.column("span").to_pylist()
            pieces = [texts[o][a : a + n] for o, a, n in zip(owner.tolist(), start, span)]
            yield pa.RecordBatch.from_arrays([flat.column("gram"), flat.column("kinds"), flat.column("single"), flat.column("start"), flat.column("place"), pa.array([a + b for a, b in zip(start, flat.column("place").to_pylist())], pa.int32()), pa.array(batch.column("row").to_numpy()[owner]), pa.array(batch.column("row2").to_numpy()[owner]), pa.array(pieces, pa.binary())], ["gram", "kinds", "single", "start", "place", "anchor", "row", "row2", "bytes"])

    # identical rows share their key: one of them is enough
    contexts = docs.join(per_row, ["row", "row2"]).select("row", "row2", "text", "w").mapInArrow(cut, "gram long, kinds long, single boolean, start int, place short, anchor int, row long, row2 long, bytes binary").dropDuplicates(["gram", "row", "row2", "start"])
    contexts = saved(contexts, "context-bytes", few_files=True)
    repeated = kinds.filter("n > 1").select("gram", "ctx", "ctx2", "n")
    whole = keyed_join(found, repeated, ["gram", "ctx", "ctx2"], "n", found.count(), "left_semi").select("row", "row2", "start", (F.col("start") + F.col("span")).alias("stop"))
    return whole.unionAll(_spans(contexts, length))


def merged(starts: np.ndarray, stops: np.ndarray) -> list[tuple[int, int]]:
    """Maximal runs that the spans cover; runs that touch are one."""
    if not len(starts):
        return []
    order = np.argsort(starts, kind="stable")
    a, b = starts[order], np.maximum.accumulate(stops[order])
    head = np.append(True, a[1:] > b[:-1])
    return list(zip(a[head].tolist(), b[np.append(head[1:], True)].tolist()))


def remove_repeats(docs: DataFrame, length: int = 200) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and ``kept`` (the bytes that remain) of every row of ``docs``."""
    row, row2 = row_identity("doc_id", "text")
    docs = docs.select("doc_id", "text", row.alias("row"), row2.alias("row2"))
    # one span a place, however many equal rows have it; saved, so that the joins that found the spans are off the disks before
    # texts are dealt to them
    spans = repeated_spans(docs.select("row", "row2", "text"), length).groupBy("row", "row2", "start").agg(F.max("stop").alias("stop"))
    spans = saved(spans, "spans", few_files=True).groupBy("row", "row2").agg(F.collect_list("start").alias("starts"), F.collect_list("stop").alias("stops"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple[int, int, int, str, bytes]] = []
            for text, starts, stops in zip(_encode(batch.column("text")), batch.column("starts"), batch.column("stops")):
                runs = merged(np.array(starts.as_py(), np.int64), np.array(stops.as_py(), np.int64)) if starts.is_valid else []
                kept, at = [], 0
                for a, b in runs:
                    kept.append(text[at:a])
                    at = b
                rest = b"".join([*kept, text[at:]])
                out.append((len(text), len(text) - len(rest), len(runs), hashlib.sha256(rest).hexdigest(), rest))
            n, gone, runs_, sha, rest_ = zip(*out) if out else [[]] * 5
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(runs_, pa.int64()), pa.array(sha, pa.string()), pa.array(rest_, pa.binary())],
                ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"],
            )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.join(spans, ["row", "row2"], "left").select("doc_id", "text", "starts", "stops").mapInArrow(run, f"doc_id {kind}, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")
