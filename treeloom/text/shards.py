"""Sharded full-text indexes: whole texts, 32 MB and more a shard in production, one row a shard.

Texts are never split, so counts are sums over shards and answers disjoint unions.  Every search takes a batch of
patterns and passes once over the shards; shards whose id range misses the asked one are pruned by their columns.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treeloom.text.fm import TextIndex, merge

SHARD_BYTES = 32 << 20
#: Few, so that no task is left to run alone at the end.
TASK_SHARDS = 4
SHARD_SCHEMA = "first_text long, last_text long, n_texts long, n_bytes long, sample int, kind string, ids binary, data binary, text_bits long, sample_bits long, doc_bits long"


def _row(ids: list[int], ix: TextIndex) -> tuple:
    s = ix.sizes()
    return (ids[0], ids[-1], len(ids), ix.n, ix.sample, ix.kind, np.array(ids, np.int64).tobytes(), ix.pack(), s["text"], s["samples"], s["doc"])


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.int64()] * 4 + [pa.int32(), pa.string(), pa.binary(), pa.binary()] + [pa.int64()] * 3
    names = [x.split()[0] for x in SHARD_SCHEMA.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names)


def one_by_one(batch: pa.RecordBatch, *columns: str) -> Iterator[tuple]:
    """The values of each row of a batch; those of one row are in memory at a time."""
    return (tuple(batch.column(c)[i].as_py() for c in columns) for i in range(batch.num_rows))


def build_shards(texts: DataFrame, sample: int = 64, kind: str = "blocks", shard_bytes: int = SHARD_BYTES, partitions: int | None = None, group: str = "0") -> DataFrame:
    """Index of ``texts(text_id, value)``; null texts are left out.  ``partitions``: tasks at least; more where one would get over ``TASK_SHARDS``
    shards.  No shard holds texts of more than one ``group``, a number that ``text_id`` gives."""
    rows = texts.filter("value is not null").select(F.col("text_id").cast("long").alias("text_id"), "value").withColumn("group", F.expr(group).cast("long"))
    if partitions:
        n_bytes = rows.agg(F.sum(F.octet_length("value"))).first()[0] or 0
        partitions = max(partitions, -(-n_bytes // (TASK_SHARDS * shard_bytes)))
    by = ["text_id"] if group == "0" else ["group", "text_id"]
    rows = (rows.repartitionByRange(partitions, *by) if partitions else rows.repartitionByRange(*by)).sortWithinPartitions(*by)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids: list[int] = []
        held: list[bytes] = []
        size, own = 0, None
        for batch in batches:
            for i, v, g in zip(batch.column("text_id").to_pylist(), batch.column("value").cast(pa.binary()).to_pylist(), batch.column("group").to_pylist()):
                if held and (size + len(v) > shard_bytes or g != own):
                    yield _batch([_row(ids, TextIndex.build(held, sample, kind))])
                    ids, held, size = [], [], 0
                own = g
                ids.append(i)
                held.append(v)
                size += len(v) + 1
        if held:
            yield _batch([_row(ids, TextIndex.build(held, sample, kind))])

    return rows.mapInArrow(run, SHARD_SCHEMA)


def compact(shards: DataFrame, group: int = 2) -> DataFrame:
    """Merges each ``group`` neighbouring shards by interleaving their rows."""
    numbered = shards.repartitionByRange(1, "first_text").sortWithinPartitions("first_text") if group == 0 else shards.repartitionByRange("first_text").sortWithinPartitions("first_text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids: list[int] = []
        held: TextIndex | None = None
        n = 0
        for batch in batches:
            for raw, data in one_by_one(batch, "ids", "data"):
                ix = TextIndex.unpack(data)
                held = ix if held is None else merge(held, ix)
                ids += np.frombuffer(raw, np.int64).tolist()
                n += 1
                if group and n == group:
                    yield _batch([_row(ids, held)])
                    ids, held, n = [], None, 0
        if held is not None:
            yield _batch([_row(ids, held)])

    return numbered.mapInArrow(run, SHARD_SCHEMA)


#: What each question asks of a shard; all but the counts give text ids.
_ASK = {
    "contains": TextIndex.contains, "starts-with": TextIndex.starts_with, "ends-with": TextIndex.ends_with, "=": TextIndex.equals,
    "<": lambda ix, p: ix.compare("<", p), "<=": lambda ix, p: ix.compare("<=", p), ">": lambda ix, p: ix.compare(">", p), ">=": lambda ix, p: ix.compare(">=", p),
}


def search(shards: DataFrame, op: str, patterns: list[str], ids: tuple[int | None, int | None] = (None, None), errors: int = 0) -> DataFrame:
    """(pattern, text_id) of the texts that satisfy ``op``; ``ids`` restricts to a range of text ids."""
    low, high = ids
    if low is not None:
        shards = shards.filter(F.col("last_text") >= low)
    if high is not None:
        shards = shards.filter(F.col("first_text") <= high)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw, data in one_by_one(batch, "ids", "data"):
                ix, own = TextIndex.unpack(data), np.frombuffer(raw, np.int64)
                x = int(np.searchsorted(own, low)) if low is not None else None
                y = int(np.searchsorted(own, high, "right")) - 1 if high is not None else None
                for p in patterns:
                    hits = ix.approximate(p, errors) if op == "approximate" else ix.within_edits(p, errors) if op == "edits" else _ASK[op](ix, p)
                    found = own[ix.in_range(hits, x, y)]
                    yield pa.RecordBatch.from_arrays([pa.array([p] * len(found), pa.string()), pa.array(found)], ["pattern", "text_id"])

    return shards.select("ids", "data").mapInArrow(run, "pattern string, text_id long")


def counts(shards: DataFrame, patterns: list[str]) -> DataFrame:
    """pattern, occurrences (GlobalCount), texts (ContainsCount)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for (data,) in one_by_one(batch, "data"):
                ix = TextIndex.unpack(data)
                rows = [(p, ix.global_count(p), len(ix.contains(p))) for p in patterns]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), (pa.string(), pa.int64(), pa.int64()))], ["pattern", "o", "t"])

    return shards.select("data").mapInArrow(run, "pattern string, o long, t long").groupBy("pattern").agg(F.sum("o").alias("occurrences"), F.sum("t").alias("texts"))


def global_count(shards: DataFrame, patterns: list[str], group: str = "0") -> DataFrame:
    """pattern, occurrences: one backward search a shard and pattern, nothing is located.  With a ``group`` of ``build_shards``: group as well."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for g, data in one_by_one(batch, "group", "data"):
                ix = TextIndex.unpack(data)
                yield pa.RecordBatch.from_arrays([pa.array([g] * len(patterns), pa.int64()), pa.array(patterns, pa.string()), pa.array([ix.global_count(p) for p in patterns], pa.int64())], ["group", "pattern", "o"])

    asked = shards.select(group_of(group).alias("group"), "data").mapInArrow(run, "group long, pattern string, o long")
    return asked.groupBy(*(["pattern"] if group == "0" else ["group", "pattern"])).agg(F.sum("o").alias("occurrences"))


def group_of(group: str) -> Column:
    """The group of a shard, which is that of its first text."""
    return F.expr(group.replace("text_id", "first_text")).cast("long")


def locate(shards: DataFrame, pattern: str) -> DataFrame:
    """text_id, offset (in bytes, from 0) of every occurrence."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw, data in one_by_one(batch, "ids", "data"):
                ix = TextIndex.unpack(data)
                text, offset = ix.locate(np.arange(*ix.search(pattern)))
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(raw, np.int64)[text]), pa.array(offset)], ["text_id", "offset"])

    return shards.select("ids", "data").mapInArrow(run, "text_id long, offset long")


def matrix(shards: DataFrame, weights: list[dict[str, int]], threshold: int) -> DataFrame:
    """text_id of texts with a window that scores over ``threshold``, by backtracking in the index: branches whose best possible score
    is too low are never entered."""
    coded = [{ord(c): w for c, w in column.items()} for column in weights]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw, data in one_by_one(batch, "ids", "data"):
                ix = TextIndex.unpack(data)
                text, _ = ix.locate(ix.matrix(coded, threshold))
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(raw, np.int64)[np.unique(text)])], ["text_id"])

    return shards.select("ids", "data").mapInArrow(run, "text_id long")


def extract(shards: DataFrame) -> DataFrame:
    """text_id, value: every text read back from its index."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw, data in one_by_one(batch, "ids", "data"):
                ix = TextIndex.unpack(data)
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(raw, np.int64)), pa.array([t.decode() for t in ix.extract_all()], pa.string())], ["text_id", "value"])

    return shards.select("ids", "data").mapInArrow(run, "text_id long, value string")


def sizes(shards: DataFrame) -> DataFrame:
    """Bits a text byte of each part of the index."""
    total = F.sum("n_bytes")
    part = lambda c: F.round(F.sum(c) / total, 4).alias(c.replace("_bits", "_bits_per_byte"))
    return shards.groupBy("kind", "sample").agg(total.alias("n_bytes"), part("text_bits"), part("sample_bits"), part("doc_bits"))
