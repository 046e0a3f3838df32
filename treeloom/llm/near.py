"""Near duplicates by HyperMinHash.

A document's set holds the distinct k-word shingles of its whole text.  One 64-bit hash a shingle falls, by its leading
bits, into one of ``M`` buckets; a bucket keeps the leading-zero count of its least remainder and the mantissa bits
behind it, in 16 bits (0: empty).  Empty buckets borrow from a fixed sequence of others and, if all are empty, take a hash of
their own over the shingles, so that a band never stands for one common shingle of a short text.  Bands of compressed registers give candidates.  Of those, pairs go whose
own registers differ in more places than sets at the threshold can, and pairs that the collision-corrected
estimate puts far below the threshold; the rest are confirmed on the full sets.

Equal sets are one class, a node with a number of its own, before any pair is formed.  Pairs are formed in two steps.
First each band bucket ties its members to its least node, which is linear in the rows whatever the size of a bucket.
Then, with the components of those links, members of one bucket that are still in different components are
compared by their registers where the bucket lies, block against block, and only pairs that can reach the threshold come
out, so that no link between components is lost and no pair within one is formed.  In buckets of several blocks only members
of neighbouring size classes meet, since sets at the threshold differ in size by less than one class.

With ``BANDS`` bands of ``ROWS`` independent slots a pair at the threshold escapes with probability (1 - 0.8^4)^32 < 1e-7.

Rows without words have an empty set and are linked with nothing.  Rows that share an id are one document and share its
component, whatever their texts.  A null id counts as larger than all others; a component of such rows alone has a null id.
Ids may be of any type that sorts.  An empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treeloom.llm.store import discard, fresh, keyed_join, lean, row_identity, saved, shuffles_removed

BANDS, ROWS = 32, 4
BUCKET_BITS = 9
M = 1 << BUCKET_BITS
#: Members of a band bucket that one task compares with as many others.
BLOCK_MEMBERS = 1024
REST = 64 - BUCKET_BITS
MANTISSA = 10
#: Estimates so many standard deviations below the threshold end a candidate: fewer than one in 10^11 at the threshold.
SIGMAS = 7
_WORDS_CACHED = 300_000


class _WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= _WORDS_CACHED:
            self.clear()
        h = xxhash.xxh64_intdigest(word)
        if len(word) <= 64:
            self[word] = h
        return h


def _finish(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(32))


class Shingler:
    """Sorted distinct shingle hashes of texts; A-Z count as a-z, words end at blank and \\x09-\\x0D."""

    def __init__(self, k: int):
        self.k = k
        self.get = _WordHashes().__getitem__

    def __call__(self, text: str | None) -> np.ndarray:
        words = (text or "").encode("utf-8", "surrogatepass").lower().split()
        h = np.fromiter(map(self.get, words), np.uint64, len(words))
        n = min(self.k, len(h))
        if not n:
            return h
        acc = np.full(len(h) - n + 1, n, np.uint64)
        for i in range(n):
            acc = acc * np.uint64(0x9E3779B97F4A7C15) + h[i : len(h) - n + 1 + i]
        return np.unique(_finish(acc))


_STARTS = np.arange(M, dtype=np.uint64) << np.uint64(REST)


def registers(shingles: np.ndarray) -> np.ndarray:
    """The ``M`` registers of a sorted array of hashes."""
    at = np.searchsorted(shingles, _STARTS)
    out = np.zeros(M, np.uint16)
    inside = at < len(shingles)
    least = shingles[at[inside]]
    own = (least >> np.uint64(REST)) == np.nonzero(inside)[0].astype(np.uint64)
    where = np.nonzero(inside)[0][own]
    rest = least[own] & np.uint64((1 << REST) - 1)
    bits = np.frexp(rest.astype(np.float64))[1]
    zeros = np.clip(REST - bits, 0, REST)
    mantissa = (rest >> np.maximum(bits - 1 - MANTISSA, 0).astype(np.uint64)) & np.uint64((1 << MANTISSA) - 1)
    out[where] = 1 + (zeros << MANTISSA) + mantissa.astype(np.int64)
    return out


#: Where an empty register looks for a value, attempt by attempt.
_BORROW = np.random.default_rng(20).integers(0, M, (64, BANDS * ROWS))


#: One odd multiplier and one offset a slot, for what no attempt has filled.
_FRESH = np.random.default_rng(21).integers(0, 1 << 63, (2, BANDS * ROWS), np.uint64) * np.uint64(2) + np.uint64(1)


def borrowed(regs: np.ndarray, shingles: np.ndarray) -> np.ndarray:
    """The registers of the bands, each empty one filled from the first filled one of its sequence.

    A slot that finds none takes the least of its own hash of the shingles, so that no two slots fall back on one register."""
    out = regs[: BANDS * ROWS].copy()
    empty = np.nonzero(out == 0)[0]
    for look in _BORROW:
        if not len(empty):
            return out
        out[empty] = regs[look[empty]]
        empty = empty[out[empty] == 0]
    if len(empty) and len(shingles):
        least = _finish(shingles * _FRESH[0, empty, None] + _FRESH[1, empty, None]).min(axis=1)
        out[empty] = np.maximum(least & np.uint64(0xFFFF), np.uint64(1)).astype(np.uint16)
    return out


def expected_collisions(n1: np.ndarray, n2: np.ndarray) -> np.ndarray:
    """Registers in which disjoint sets of n1 and n2 shingles agree by chance: over each leading-zero count, both
    least values fall there and share their mantissa."""
    z = np.arange(REST + 1)[None, :]
    hi, lo = 2.0**-z, np.where(z < REST, 2.0 ** -(z + 1.0), 0.0)

    def falls(n: np.ndarray) -> np.ndarray:
        n = n[:, None] / M
        return np.exp(-n * lo) - np.exp(-n * hi)

    return M * (falls(n1) * falls(n2)).sum(axis=1) / (1 << MANTISSA)


def estimate(r1: np.ndarray, r2: np.ndarray, n1: np.ndarray, n2: np.ndarray) -> np.ndarray:
    """Jaccard estimates of pairs of register rows, chance agreement taken off."""
    used = ((r1 > 0) | (r2 > 0)).sum(axis=1)
    same = ((r1 == r2) & (r1 > 0)).sum(axis=1)
    chance = expected_collisions(n1, n2)
    return np.clip((same - chance) / np.maximum(used - chance, 1e-9), 0, 1)


def signatures(docs: DataFrame, k: int) -> DataFrame:
    """``docs(doc_id, r1, r2, text)`` with n_shingles, digest of the set (null if empty) and the registers of its bands for the text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(k)
        for batch in batches:
            n, digest, full = [], [], []
            for text in batch.column("text"):
                s = shingler(text.as_py())
                n.append(len(s))
                digest.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
                full.append(borrowed(registers(s), s).tobytes() if len(s) else None)
            made = [pa.array(n, pa.int64()), pa.array(digest, pa.binary()), pa.array(full, pa.binary())]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("doc_id", "r1", "r2")), *made], ["doc_id", "r1", "r2", "n_shingles", "digest", "full"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "r1", "r2", "text").mapInArrow(lean(run), f"doc_id {kind}, r1 long, r2 long, n_shingles long, digest binary, full binary")


def sketches(texts: DataFrame, k: int) -> DataFrame:
    """node, text, n_shingles, all registers and those of the bands of ``texts(node, text)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(k)
        for batch in batches:
            sets = [shingler(t.as_py()) for t in batch.column("text")]
            regs = [registers(s) for s in sets]
            made = [pa.array([len(s) for s in sets], pa.int64()), pa.array([r.tobytes() for r in regs], pa.binary()), pa.array([borrowed(r, s).tobytes() if len(s) else None for r, s in zip(regs, sets)], pa.binary())]
            yield pa.RecordBatch.from_arrays([batch.column("node"), batch.column("text"), *made], ["node", "text", "n_shingles", "regs", "full"])

    return texts.select("node", "text").mapInArrow(lean(run), "node long, text string, n_shingles long, regs binary, full binary")


def possible(r1: np.ndarray, r2: np.ndarray, n1: np.ndarray, n2: np.ndarray, threshold: float) -> np.ndarray:
    """Pairs of register rows that may reach the threshold."""
    # each register that differs takes a shingle that the sets do not share
    fits = (r1 != r2).sum(axis=1) <= (n1 + n2) * (1 - threshold) / (1 + threshold) + 1e-9
    fits &= np.minimum(n1, n2) + 1e-9 >= threshold * np.maximum(n1, n2)
    at = np.nonzero(fits)[0]
    # the fewer registers are in use, the coarser the estimate
    used = np.maximum(((r1[at] > 0) | (r2[at] > 0)).sum(axis=1), 1)
    fits[at] = estimate(r1[at], r2[at], n1[at], n2[at]) >= threshold - SIGMAS * np.sqrt(threshold * (1 - threshold) / used)
    return fits


def _rows(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint16).reshape(-1, M)


def likely_pairs(pairs: DataFrame, known: DataFrame, threshold: float) -> DataFrame:
    """The (u, w) that may reach the threshold by the registers in ``known``."""
    a = known.select(F.col("node").alias("u"), F.col("n_shingles").alias("nu"), F.col("regs").alias("ru"))
    b = known.select(F.col("node").alias("w"), F.col("n_shingles").alias("nw"), F.col("regs").alias("rw"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                fits = possible(_rows(batch.column("ru")), _rows(batch.column("rw")), batch.column("nu").to_numpy(), batch.column("nw").to_numpy(), threshold)
                yield batch.select(["u", "w"]).filter(pa.array(fits))

    return pairs.join(b, "w").join(a, "u").select("u", "w", "nu", "nw", "ru", "rw").mapInArrow(lean(run), "u long, w long")


def dealt_blocks(apart: DataFrame, threshold: float) -> DataFrame:
    """Rows of ``apart(key, band, id, label, n_shingles)`` once for each pair of blocks (i, j) of a group that they are in.

    A bucket of one block is one group.  A larger one has a group for each size class, with the members of that class and, as
    ``high``, those of the next: sets at the threshold differ by a factor of less than one class.
    """
    buckets = apart.groupBy("key").agg(F.count("*").alias("members"))
    size_class = F.floor(F.log(F.col("n_shingles").cast("double")) / -float(np.log(threshold))).cast("int")
    low, high = F.struct(F.col("c").alias("grp"), F.lit(False).alias("high")), F.struct((F.col("c") - 1).alias("grp"), F.lit(True).alias("high"))
    whole = F.struct(F.lit(-2).alias("grp"), F.lit(False).alias("high"))
    rows = apart.join(buckets, "key").withColumn("c", size_class)
    rows = rows.withColumn("x", F.explode(F.when(F.col("members") > BLOCK_MEMBERS, F.array(low, high)).otherwise(F.array(whole)))).select("key", "band", "x.grp", "x.high", "id", "label")
    groups = rows.groupBy("key", "grp").agg(F.ceil(F.count("*") / BLOCK_MEMBERS).cast("int").alias("nb"), F.count_if(~F.col("high")).alias("lows")).filter("lows > 0").drop("lows")
    rows = rows.join(groups, ["key", "grp"]).withColumn("b", F.pmod(F.xxhash64("id"), F.col("nb")).cast("int"))
    # block b meets every block: as the first of the two up from b, as the second below it
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)))
    return rows.select("key", "band", "grp", "high", F.least("b", "other").alias("i"), F.greatest("b", "other").alias("j"), "b", "id", "label")


def pairs_across(apart: DataFrame, known: DataFrame, threshold: float) -> DataFrame:
    """The (u, w), u < w, of one bucket of ``apart(key, band, id, label, n_shingles)`` but of different labels that may reach the threshold.

    A bucket of many members is dealt as pairs of blocks, so that a task compares at most ``BLOCK_MEMBERS`` with as many.
    A pair comes out of the first band that it shares, once.
    """
    rows = dealt_blocks(apart, threshold)
    sketched = rows.join(known.select(F.col("node").alias("id"), "n_shingles", "regs", "full"), "id")

    def compare(t: pa.Table) -> Iterator[pa.RecordBatch]:
        ids, label, n, b = (t.column(c).to_numpy() for c in ("id", "label", "n_shingles", "b"))
        high = t.column("high").to_numpy(zero_copy_only=False)
        regs = _rows(t.column("regs").combine_chunks())
        bands = np.frombuffer(b"".join(t.column("full").to_pylist()), np.uint64).reshape(-1, BANDS)
        band = t.column("band")[0].as_py()
        same_block = t.column("i")[0].as_py() == t.column("j")[0].as_py()
        for x in range(len(ids)):
            other = (label != label[x]) & ((ids > ids[x]) if same_block else (b > b[x]))
            if high[x]:
                other &= ~high
            y = np.nonzero(other & (np.minimum(n, n[x]) + 1e-9 >= threshold * np.maximum(n, n[x])))[0]
            if band and len(y):
                y = y[~(bands[y, :band] == bands[x, :band]).any(axis=1)]
            if len(y):
                y = y[possible(np.broadcast_to(regs[x], (len(y), M)), regs[y], np.full(len(y), n[x]), n[y], threshold)]
                if len(y):
                    yield pa.RecordBatch.from_arrays([pa.array(np.minimum(ids[x], ids[y])), pa.array(np.maximum(ids[x], ids[y]))], ["u", "w"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held_: pa.Table | None = None
        for batch in batches:
            if not batch.num_rows:
                continue
            t = pa.Table.from_batches([batch])
            t = t if held_ is None else pa.concat_tables([held_, t])
            unit = np.stack([t.column(c).to_numpy() for c in ("key", "grp", "i", "j")])
            cuts = [0, *(np.nonzero((unit[:, 1:] != unit[:, :-1]).any(axis=0))[0] + 1).tolist()]
            for s, e in zip(cuts, cuts[1:]):
                yield from compare(t.slice(s, e - s))
            held_ = t.slice(cuts[-1])
        if held_ is not None:
            yield from compare(held_)

    dealt = sketched.repartition("key", "grp", "i", "j").sortWithinPartitions("key", "grp", "i", "j")
    return dealt.select("key", "band", "grp", "high", "i", "j", "b", "id", "label", "n_shingles", "regs", "full").mapInArrow(lean(run), "u long, w long").distinct()


def confirmed(pairs: DataFrame, texts: DataFrame, k: int, percent: int) -> DataFrame:
    """The (u, w) with 100 * shared >= percent * union on the full shingle sets."""
    a = texts.select(F.col("node").alias("u"), F.col("text").alias("tu"))
    b = texts.select(F.col("node").alias("w"), F.col("text").alias("tw"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(k)
        last_id, last = None, None
        for batch in batches:
            keep = []
            for u, tu, tw in zip(batch.column("u").to_pylist(), batch.column("tu"), batch.column("tw")):
                if u != last_id:
                    last_id, last = u, shingler(tu.as_py())
                other = shingler(tw.as_py())
                shared = len(np.intersect1d(last, other, assume_unique=True))
                keep.append(100 * shared >= percent * (len(last) + len(other) - shared))
            yield batch.select(["u", "w"]).filter(pa.array(keep, pa.bool_()))

    return pairs.join(b, "w").join(a, "u").select("u", "w", "tu", "tw").mapInArrow(lean(run), "u long, w long")


def components(links: DataFrame) -> DataFrame:
    """node, label (smallest id of its component) of every node of ``links(u, w)``; alternating star contraction.

    It ends when every node leads to one other, which leads nowhere: the edges are then stars around the labels.
    """
    edges = links.select(F.greatest("u", "w").alias("a"), F.least("u", "w").alias("b")).filter("a <> b")
    spent: DataFrame | None = None
    while True:
        both = edges.unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(least, "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("x")).select("x.*").filter("a <> b").distinct()
        edges = saved(small, "edges", few_files=True)
        if spent is not None:
            discard(spent)
        spent = edges
        forked = edges.groupBy("a").agg(F.min("b").alias("lo"), F.max("b").alias("hi")).filter("lo < hi").select("a")
        onward = edges.select(F.col("b").alias("a")).join(edges.select("a"), "a", "left_semi")
        with shuffles_removed(edges.sparkSession):
            done = forked.unionAll(onward).isEmpty()
        if done:
            break
    return edges.select(F.col("a").alias("node"), F.col("b").alias("label")).unionAll(edges.select(F.col("b").alias("node"), F.col("b").alias("label")).distinct())


def _bands(reps: DataFrame) -> DataFrame:
    width = 2 * ROWS
    slices = F.array(*[F.struct(F.substring("full", 1 + i * width, width).alias("s"), F.lit(i).alias("i")) for i in range(BANDS)])
    return reps.select("node", F.explode(slices).alias("x")).select(F.xxhash64("x.i", "x.s").alias("key"), F.col("x.i").alias("band"), F.col("node").alias("id"))


def _same_id(fine: DataFrame, reps: DataFrame) -> DataFrame | None:
    """Links (u, w) between the classes of the rows of one id; None if no id has two."""
    ids = fine.filter("doc_id is not null").select("doc_id", "digest").distinct()
    several = ids.groupBy("doc_id").agg(F.count("*").alias("c")).filter("c > 1").select("doc_id")
    several = saved(ids.join(several, "doc_id", "left_semi"), "same-id", few_files=True)
    if several.isEmpty():
        return None
    nodes = several.join(reps.select("digest", "node"), "digest")
    least = nodes.groupBy("doc_id").agg(F.min("node").alias("u"))
    return nodes.join(least, "doc_id").filter("u < node").select("u", F.col("node").alias("w")).distinct()


def _linked_classes(docs: DataFrame, sig: DataFrame, fine: DataFrame, reps: DataFrame, k: int, percent: int) -> DataFrame:
    """node, label: the component of every class that is linked with another."""
    bands = _bands(reps)
    full = bands.groupBy("key").agg(F.min("id").alias("lead"), F.max("id").alias("last")).filter("lead < last")
    members = saved(bands.join(full, "key").select("key", "band", "id", "lead"), "members", few_files=True)
    star = members.filter("id <> lead").select(F.col("lead").alias("u"), F.col("id").alias("w")).distinct()
    in_pairs = reps.join(members.select(F.col("id").alias("node")).distinct(), "node").select("node", "one.r1", "one.r2")
    texts = docs.select("r1", "r2", "text").join(in_pairs, ["r1", "r2"]).select("node", "text")
    # rows that agree in id and text come several times: one is enough
    texts = saved(sketches(texts, k).dropDuplicates(["node"]), "texts", few_files=True)
    threshold = percent / 100
    links = confirmed(likely_pairs(star, texts, threshold), texts, k, percent)
    same = _same_id(fine, reps)
    links = saved(links if same is None else links.unionAll(same), "links", few_files=True)
    label = components(links)
    apart = members.select("key", "band", "id").join(label.withColumnRenamed("node", "id"), "id", "left").withColumn("label", F.coalesce("label", "id"))
    mixed = apart.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).filter("lo < hi").select("key")
    sizes = texts.select(F.col("node").alias("id"), "n_shingles")
    mixed = saved(apart.join(mixed, "key", "left_semi").join(sizes, "id"), "mixed", few_files=True)
    across = pairs_across(mixed, texts, threshold)
    more = saved(confirmed(across.join(star, ["u", "w"], "left_anti"), texts, k, percent), "links", few_files=True)
    discard(mixed, members, texts)
    return saved(components(links.unionAll(more)), "labels", few_files=True)


def linked_rows(docs: DataFrame, k: int, percent: int) -> DataFrame:
    """r1, r2, doc_id, n_shingles, component (null without words) and component_id of every row of ``docs(doc_id, r1, r2, text)``."""
    sig = saved(signatures(docs, k), "signatures")
    fine = sig.filter("digest is not null")
    one = F.min(F.struct("r1", "r2")).alias("one")
    reps = fine.groupBy("digest").agg(F.min("doc_id").alias("least"), F.count("*").alias("n"), F.first("full").alias("full"), one)
    # numbered as they are written: one number a class, whatever is computed again
    reps = saved(reps.withColumn("node", F.monotonically_increasing_id()), "reps")
    label = _linked_classes(docs, sig, fine, reps, k, percent)
    named = label.join(reps.select("node", "least"), "node")
    named = saved(named.groupBy("label").agg(F.min("least").alias("component_id"), F.count("*").alias("c")), "components", few_files=True)
    own = keyed_join(label, named, ["label"], "c", label.count())
    classes = reps.select("digest", "n", "node", "least").join(own, "node", "left")
    # a class of its own has its least id; one that is linked the least of its component, null only if no row has an id
    classes = classes.select("digest", "n", F.coalesce("label", "node").alias("component"), F.when(F.col("label").isNull(), F.col("least")).otherwise(F.col("component_id")).alias("component_id"))
    classes = saved(classes, "classes")
    rows = sig.select("digest", "r1", "r2", "doc_id", "n_shingles")
    alone = rows.filter("digest is null").select("r1", "r2", "doc_id", "n_shingles", F.lit(None).cast("long").alias("component"), F.col("doc_id").alias("component_id"))
    return keyed_join(rows.filter("digest is not null"), classes, ["digest"], "n", sig.count()).select(*alone.columns).unionByName(alone)


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest id reachable over links), kept (doc_id = component_id) of every row."""
    r1, r2 = row_identity("doc_id", "text")
    rows = linked_rows(docs.select("doc_id", r1.alias("r1"), r2.alias("r2"), "text"), k, percent)
    return rows.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def drop_near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """One row of each group of near duplicates, all columns of ``docs``: the one with the least id, of several the least by a
    hash of id and text.  Rows without words all stay."""
    columns = [F.col(f"`{c}`") for c in docs.columns]
    n1, n2 = fresh(docs.columns, "r1", "r2")
    r1, r2 = row_identity("doc_id", "text")
    keyed = docs.select(*columns, r1.alias(n1), r2.alias(n2))
    rows = saved(linked_rows(keyed.select("doc_id", F.col(n1).alias("r1"), F.col(n2).alias("r2"), "text"), k, percent), "rows").filter("component is not null")
    keeper = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "r1", "r2")).alias("k")
    first = saved(rows.groupBy("component").agg(keeper, F.count("*").alias("n")).select("k.r1", "k.r2", "component", "n"), "keepers")
    # equal rows: only these need their columns to be gathered, one row a key with sums before the shuffle
    again = saved(rows.join(first.filter("n > 1"), ["r1", "r2"], "left_semi").groupBy("r1", "r2").agg(F.count("*").alias("n")).filter("n > 1"), "again", few_files=True)
    gone = rows.select("r1", "r2").join(first.hint("merge"), ["r1", "r2"], "left_anti").distinct().hint("merge")
    to_own = lambda df: df.select(F.col("r1").alias(n1), F.col("r2").alias(n2))
    kept = keyed.join(to_own(gone), [n1, n2], "left_anti")
    if again.isEmpty():
        return kept.select(*columns)
    repeated = kept.join(to_own(again), [n1, n2], "left_semi")
    single = repeated.groupBy(n1, n2).agg(F.min_by(F.struct(*columns), F.xxhash64(*columns)).alias("x")).select("x.*")
    return kept.join(to_own(again), [n1, n2], "left_anti").select(*columns).unionAll(single)
