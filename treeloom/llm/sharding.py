"""Exact uniform shards from a hypergeometric communication matrix, with DataFrame functions only.

Rows fall into source blocks by a hash of their content.  Of each block only the row count reaches the driver, where
a matrix of (block, cell) counts is drawn: block after block takes a multivariate hypergeometric share of the room
that is left in the cells.  A cell is a slice of a shard; cell sizes are fixed beforehand, so shards are exact.
Each block is permuted, its first rows go to the first cell by the drawn count, and so on; each cell is permuted
again, and a row's place in it is its slot.  Both permutations order by seeded hashes, so a rerun after a lost
executor gives the same rows the same places.

The numbers of blocks and cells are bounded (``MAX_BLOCKS``), so the matrix is bounded too.  Where blocks or cells outgrow ``BLOCK_ROWS``,
ranks are counted in buckets of the order hash and added up, so that no task sorts more than a bucket.  The table with its hashes
is saved first, so that all steps see the same.  Rows that agree in all columns share a hash; where they are many, a number of their
own goes into it, and they are dealt like any others.
Null texts have size 1; an empty table gives no rows.
"""

from __future__ import annotations

import math
import random

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from treeloom.llm.store import HOT_KEYS, fresh, literal_table, saved

BLOCK_ROWS = 1 << 13
MAX_BLOCKS = 1 << 10
_NUMPY_LIMIT = 10**9


def hypergeometric(rng: random.Random, good: int, bad: int, drawn: int) -> int:
    """Good ones among ``drawn`` of ``good + bad``, by inversion outward from the mode; for any size."""
    low, high = max(0, drawn - bad), min(good, drawn)
    mode = min(high, max(low, (drawn + 1) * (good + 1) // (good + bad + 2)))

    def log_choose(n: int, k: int) -> float:
        return math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)

    peak = math.exp(log_choose(good, mode) + log_choose(bad, drawn - mode) - log_choose(good + bad, drawn))
    u = rng.random() - peak
    up = down = mode
    p_up = p_down = peak
    while u > 0 and (up < high or down > low):
        if up < high:
            p_up *= (good - up) * (drawn - up) / ((up + 1) * (bad - drawn + up + 1))
            up += 1
            u -= p_up
            if u <= 0:
                return up
        if down > low:
            p_down *= down * (bad - drawn + down) / ((good - down + 1) * (drawn - down + 1))
            down -= 1
            u -= p_down
            if u <= 0:
                return down
    return mode


def communication_matrix(block_rows: list[int], cell_rows: list[int], seed: int) -> np.ndarray:
    """Counts (block, cell) with the given margins, as a uniform shuffle of all rows would give them."""
    room = np.array(cell_rows, np.int64)
    out = np.zeros((len(block_rows), len(cell_rows)), np.int64)
    fast, exact = np.random.Generator(np.random.PCG64(seed)), random.Random(seed)
    for b, n in enumerate(block_rows):
        if int(room.sum()) < _NUMPY_LIMIT:
            out[b] = fast.multivariate_hypergeometric(room, n, method="marginals")
        else:
            left, total = n, int(room.sum())
            for c, r in enumerate(map(int, room)):
                total -= r
                out[b, c] = hypergeometric(exact, r, total, left) if left and total else left
                left -= int(out[b, c])
        room -= out[b]
    return out


def _position(starts: Column, rank: Column) -> Column:
    """Index of the last start that is at most ``rank``."""
    return F.size(F.filter(starts, lambda x: x <= rank)) - 1


def _ranked(df: DataFrame, group: str, order: Column, tie: str, bits: int, rank: str) -> DataFrame:
    """``df`` with ``rank`` (from 0) in its group by ``order``, a 64-bit hash, then ``tie``; 2^bits buckets a group."""
    by = [order, F.col(tie)]  # equal hashes are equal rows
    if not bits:
        return df.withColumn(rank, (F.row_number().over(Window.partitionBy(group).orderBy(*by)) - 1).cast("long"))
    g, bucket, n, first = fresh(df.columns, "group", "bucket", "n", "first")
    rows = df.withColumn(bucket, F.shiftright(order, 64 - bits).cast("int"))
    sizes = rows.groupBy(F.col(group).alias(g), bucket).agg(F.count("*").alias(n))
    starts = sizes.withColumn(first, F.sum(n).over(Window.partitionBy(g).orderBy(bucket)) - F.col(n)).select(g, F.col(bucket).alias(n), first)
    inside = rows.withColumn(rank, F.row_number().over(Window.partitionBy(group, bucket).orderBy(*by)) - 1)
    return inside.join(starts, (F.col(group) == F.col(g)) & (F.col(bucket) == F.col(n))).withColumn(rank, (F.col(rank) + F.col(first)).cast("long")).drop(g, n, first, bucket)


def shard_rows(df: DataFrame, n_shards: int, seed: int = 0, key: list[Column] | None = None) -> DataFrame:
    """``df`` with ``shard`` (0 to n_shards - 1; counts at most one apart) and ``slot`` (gapless from 0 in a shard).

    ``key`` are the columns whose hash places a row (all columns if not given).  Columns named shard or slot are replaced.
    """
    spark = df.sparkSession
    own = [c for c in df.columns if c.lower() not in ("shard", "slot")]
    h, tie, block, rank, starts_col, cell = fresh([*own, "shard", "slot"], "h", "tie", "block", "rank", "starts", "cell")
    df = df.select(*[F.col(f"`{c}`") for c in own])
    key = key or [F.col(f"`{c}`") for c in own]
    hashed = saved(df.withColumn(h, F.xxhash64(F.lit(seed), *key)).withColumn(tie, F.monotonically_increasing_id()), "hashed")
    total = hashed.count()
    # fewer than HOT_KEYS hashes by their share of the rows
    hot = hashed.groupBy(h).agg(F.count("*").alias(rank)).filter(F.col(rank) > max(1, total // HOT_KEYS)).select(h, F.lit(True).alias(cell))
    spread = F.when(F.col(cell), F.xxhash64(h, tie)).otherwise(F.col(h)).alias(h)
    hashed = hashed.join(F.broadcast(hot), h, "left").select(*[F.col(f"`{c}`") for c in own], spread, tie)
    if not total:
        return df.withColumn("shard", F.lit(0)).withColumn("slot", F.lit(0).cast("long")).limit(0)
    n_blocks = max(1, min(MAX_BLOCKS, math.ceil(total / BLOCK_ROWS)))
    bits = max(0, math.ceil(math.log2(total / n_blocks / BLOCK_ROWS)))
    mixed = lambda s: F.xxhash64(F.lit(seed + s), F.col(h))
    placed = hashed.withColumn(block, F.pmod(F.col(h), F.lit(n_blocks)).cast("int"))
    counts = {r[0]: r[1] for r in placed.groupBy(block).agg(F.count("*")).collect()}
    blocks = sorted(counts)
    shard_sizes = [total // n_shards + (s < total % n_shards) for s in range(n_shards)]
    per_shard = max(1, math.ceil(n_blocks / n_shards))
    cells = [(s, u, n // per_shard + (u < n % per_shard)) for s, n in enumerate(shard_sizes) for u in range(per_shard)]
    matrix = communication_matrix([counts[b] for b in blocks], [c[2] for c in cells], seed)
    starts = np.concatenate([np.zeros((len(blocks), 1), np.int64), matrix.cumsum(axis=1)[:, :-1]], axis=1)
    # empty cells share a start with their successor; the last start that fits is the cell that has the row
    plan = literal_table(spark, f"{block} int, {starts_col} array<bigint>", [(b, s.tolist()) for b, s in zip(blocks, starts)])
    dealt = _ranked(placed, block, mixed(1), tie, bits, rank).join(plan, block).withColumn(cell, _position(F.col(starts_col), F.col(rank))).drop(rank, starts_col, block)
    first = np.cumsum([0, *(c[2] for c in cells)])
    offset = [int(first[i] - first[c[0] * per_shard]) for i, c in enumerate(cells)]
    slot_of = F.array(*map(F.lit, offset))
    return (
        _ranked(dealt, cell, mixed(2), tie, bits, rank).withColumn("slot", F.col(rank) + F.element_at(slot_of, F.col(cell) + 1).cast("long"))
        .withColumn("shard", F.floor(F.col(cell) / per_shard).cast("int"))
        .select(*[F.col(f"`{c}`") for c in own], "shard", F.col("slot").cast("long").alias("slot"))
    )


def shard_digest(docs: DataFrame, n_shards: int = 16, seed: int = 0) -> DataFrame:
    """The narrow form: doc_id, size and checksum of the text, law ``rows``, shard and slot; texts are not moved."""
    text = F.col("text")
    narrow = docs.select(
        "doc_id",
        (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long").alias("size"),
        F.crc32(F.coalesce(text, F.lit("")).cast("binary")).alias("text_crc32"),
    )
    return shard_rows(narrow, n_shards, seed).select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
