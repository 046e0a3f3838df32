"""URL rules behind a sorted array of digests.

Rules (host, path prefix, verdict) become 64-bit xxhash keys of ``host + path`` in one sorted array, with the full
rule strings beside it.  A batch of URLs is probed at once: every (host suffix, path prefix of a length that some
rule has) is hashed, looked up by vectorised binary search, and a hit counts only if the stored string equals the
probed one, so that digest collisions never decide.  Workers map the array into memory from an unlinked spool file, once a
Python worker.  Rules that take more than ``MAX_PACKED_BYTES`` are dealt, as are the probes of the URLs, by the hash of host suffix
and path prefix, and each task searches the array of its part; only the probes of a URL are moved, not the URL.

The rule that fits with the longest ``host + path`` wins (then the longer host).  Null URLs and URLs without
``://`` have an empty host and path and fit no rule.  URLs that no rule fits get ``default``.
"""

from __future__ import annotations

import json
import mmap
import re
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treeloom.llm.store import keyed_join, saved

#: A packed rule set of this size is broadcast; a larger one is dealt.
MAX_PACKED_BYTES = 256 << 20

_UPPER = {c: c + 32 for c in range(65, 91)}
_URL = re.compile(r"://([^/?#]*)([^?#]*)", re.DOTALL)


def host_and_path(url: str | None) -> tuple[str, str]:
    m = _URL.search(url) if url else None
    return (m[1].translate(_UPPER), m[2]) if m else ("", "")


def _probes(host: str, path: str, lengths: list[int]) -> list[bytes]:
    """Every rule that could fit: each suffix of the host with each path prefix of a length that rules have, in bytes."""
    if not host and not path:
        return []
    labels, raw = host.split("."), path.encode()
    return [".".join(labels[k:]).encode() + b"\0" + raw[:n] for k in range(len(labels)) for n in lengths if n <= len(raw)]


class DigestArray:
    """Sorted keys, offsets into a heap of rule strings, and verdicts; one buffer, read in place."""

    def __init__(self, buffer):
        head = np.frombuffer(buffer, "<u8", 3)
        n, meta_bytes, heap_bytes = map(int, head)
        at = 24
        self.keys = np.frombuffer(buffer, "<u8", n, at)
        self.starts = np.frombuffer(buffer, "<u8", n + 1, at + 8 * n)
        at += 8 * n + 8 * (n + 1)
        meta = json.loads(bytes(buffer[at : at + meta_bytes]))
        self.path_lengths, self.verdict_names = meta["path_lengths"], meta["verdicts"]
        self.verdicts = np.frombuffer(buffer, "u1", n, at + meta_bytes)
        self.host_chars = np.frombuffer(buffer, "<u4", n, at + meta_bytes + n)
        self.heap = memoryview(buffer)[at + meta_bytes + 5 * n : at + meta_bytes + 5 * n + heap_bytes]

    @staticmethod
    def pack(rules: list[tuple[str, str, str]]) -> bytes:
        names = sorted({v for _, _, v in rules})
        # one host and path may appear once: the first verdict given holds
        unique: dict[tuple[str, str], str] = {}
        for host, path, verdict in rules:
            unique.setdefault((host, path), verdict)
        rows = sorted((xxhash.xxh64_intdigest(f"{h}\0{p}".encode()), f"{h}\0{p}".encode(), names.index(v), len(h)) for (h, p), v in unique.items())
        meta = json.dumps({"path_lengths": sorted({len(p.encode()) for _, p in unique}), "verdicts": names}).encode()
        heap = b"".join(r[1] for r in rows)
        starts = np.cumsum([0, *(len(r[1]) for r in rows)]).astype("<u8")
        out = np.array([len(rows), len(meta), len(heap)], "<u8").tobytes() + np.array([r[0] for r in rows], "<u8").tobytes() + starts.tobytes()
        out += meta + np.array([r[2] for r in rows], "u1").tobytes() + np.array([r[3] for r in rows], "<u4").tobytes() + heap
        return out

    @classmethod
    def mapped(cls, packed: bytes) -> DigestArray:
        spool = tempfile.TemporaryFile()  # noqa: SIM115 - unlinked at once, lives as long as the map
        spool.write(packed)
        spool.flush()
        return cls(mmap.mmap(spool.fileno(), len(packed), access=mmap.ACCESS_READ))

    def find(self, probes: list[bytes]) -> np.ndarray:
        """Row of each probed string, -1 if absent."""
        out = np.full(len(probes), -1, np.int64)
        if not len(self.keys) or not probes:
            return out
        digest = np.fromiter(map(xxhash.xxh64_intdigest, probes), np.uint64, len(probes))
        low, high = np.searchsorted(self.keys, digest, "left"), np.searchsorted(self.keys, digest, "right")
        for i in np.nonzero(low < high)[0]:
            for row in range(low[i], high[i]):
                if bytes(self.heap[int(self.starts[row]) : int(self.starts[row + 1])]) == probes[i]:
                    out[i] = row
        return out

    def judge(self, urls: list[str | None], default: str) -> tuple[list[str], list[str], list[str | None], list[str]]:
        parsed = [host_and_path(u) for u in urls]
        probes, owner = [], []
        for i, (host, path) in enumerate(parsed):
            own = _probes(host, path, self.path_lengths)
            probes += own
            owner += [i] * len(own)
        rows = self.find(probes)
        best: dict[int, tuple[int, int, int]] = {}
        for k in np.nonzero(rows >= 0)[0]:
            rule = probes[k].decode()
            rank = (len(rule), int(self.host_chars[rows[k]]), int(rows[k]))
            best[owner[k]] = max(rank, best.get(owner[k], rank))
        rules, verdicts = [], []
        for i in range(len(urls)):
            row = best[i][2] if i in best else -1
            rules.append(bytes(self.heap[int(self.starts[row]) : int(self.starts[row + 1])]).decode().replace("\0", "") if row >= 0 else None)
            verdicts.append(self.verdict_names[self.verdicts[row]] if row >= 0 else default)
        return [h for h, _ in parsed], [p for _, p in parsed], rules, verdicts


#: Mapped arrays of this worker by the digest of their bytes; a task of the same rules finds the array there.
_mapped: dict[bytes, DigestArray] = {}


def _shared(packed: bytes) -> DigestArray:
    digest = xxhash.xxh3_128_digest(packed)
    if digest not in _mapped:
        _mapped.clear()
        _mapped[digest] = DigestArray.mapped(packed)
    return _mapped[digest]


def packed_bytes(rules: DataFrame) -> int:
    """Bytes of the array of ``rules(host, path, verdict)``, without its fixed head."""
    return rules.agg(F.sum(F.octet_length("host") + F.octet_length("path") + F.lit(1 + 8 + 8 + 1 + 4))).first()[0] or 0


def judge_urls(pages: DataFrame, rules: list[tuple[str, str, str]] | DataFrame, default: str = "allow", id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """One row per row of ``pages``: id, host, path, the winning rule (null if none) and the verdict.

    ``rules`` is a list or a table of (host, path, verdict); of rules that repeat a host and path the first, in a table the least
    verdict, holds."""
    spark = pages.sparkSession
    if isinstance(rules, DataFrame):
        rules = rules.select("host", "path", "verdict").filter("host is not null and path is not null and verdict is not null")
        if packed_bytes(rules) > MAX_PACKED_BYTES:
            return _judge_dealt(pages, rules, default, id_col, url_col)
        rules = [tuple(r) for r in rules.groupBy("host", "path").agg(F.min("verdict").alias("verdict")).collect()]
    packed = spark.sparkContext.broadcast(DigestArray.pack(rules))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = _shared(packed.value)
        for batch in batches:
            host, path, rule, verdict = index.judge(batch.column(1).to_pylist(), default)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(x, pa.string()) for x in (host, path, rule, verdict))], [id_col, "host", "path", "rule", "verdict"])

    kind = pages.schema[id_col].dataType.simpleString()
    return pages.select(id_col, url_col).mapInArrow(run, f"`{id_col}` {kind}, host string, path string, rule string, verdict string")


#: Rules that one task searches, about.
PART_RULES = 1 << 20


def _judge_dealt(pages: DataFrame, rules: DataFrame, default: str, id_col: str, url_col: str) -> DataFrame:
    """As :func:`judge_urls`, for rules of any number: probes meet the part of the array that their own hash falls into."""
    rules = saved(rules.groupBy("host", "path").agg(F.min("verdict").alias("verdict")), "rules")
    lengths = sorted(r[0] for r in rules.select(F.octet_length("path")).distinct().collect())  # lengths of paths, few however many rules
    n_parts = max(1, -(-rules.count() // PART_RULES))
    kind = pages.schema[id_col].dataType.simpleString()

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            parsed = [host_and_path(u) for u in batch.column(2).to_pylist()]
            probes = [_probes(h, p, lengths) for h, p in parsed]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(x, pa.string()) for x in zip(*parsed)), pa.array(probes, pa.list_(pa.binary()))], ["no", id_col, "host", "path", "probes"])

    part = lambda c: F.pmod(F.xxhash64(c), F.lit(n_parts)).cast("int")
    own = F.concat(F.encode("host", "utf-8"), F.lit(b"\0"), F.encode("path", "utf-8"))
    pages_ = pages.select(F.monotonically_increasing_id().alias("no"), id_col, url_col).mapInArrow(split, f"no long, `{id_col}` {kind}, host string, path string, probes array<binary>")
    pages_ = saved(pages_, "probes")
    # a frequent probe (a large host's) is asked once: equal probes are one row
    asked = pages_.select(F.explode("probes").alias("probe")).distinct().withColumn("part", part(F.col("probe")))
    packs = rules.select(part(own).alias("part"), "host", "path", "verdict").groupBy("part")

    def search(left: pa.Table, right: pa.Table) -> pa.Table:
        index = DigestArray(DigestArray.pack(list(zip(*(right.column(c).to_pylist() for c in ("host", "path", "verdict"))))))
        probes = left.column("probe").to_pylist()
        rows = index.find(probes)
        hit = np.nonzero(rows >= 0)[0].tolist()
        found = [probes[i] for i in hit]
        return pa.table({"probe": pa.array(found, pa.binary()), "verdict": pa.array([index.verdict_names[index.verdicts[rows[i]]] for i in hit], pa.string())})

    hits = saved(asked.groupBy("part").cogroup(packs).applyInArrow(search, "probe binary, verdict string"), "hits", few_files=True)
    probed = pages_.select("no", F.explode("probes").alias("probe"))
    counts = saved(probed.join(hits.select("probe"), "probe", "left_semi").groupBy("probe").agg(F.count("*").alias("n")), "hit-probes", few_files=True)
    known = hits.join(counts, "probe")
    fits = keyed_join(probed, known, ["probe"], "n", probed.count())
    chars = lambda c: F.decode(c, "utf-8")
    length = F.length(chars(F.col("probe")))
    host = F.length(F.substring_index(chars(F.col("probe")), "\0", 1))
    best = fits.groupBy("no").agg(F.max(F.struct(length.alias("a"), host.alias("b"), "probe", "verdict")).alias("x"))
    out = pages_.join(best, "no", "left")
    return out.select(id_col, "host", "path", F.replace(chars(F.col("x.probe")), F.lit("\0"), F.lit("")).alias("rule"), F.coalesce("x.verdict", F.lit(default)).alias("verdict"))
