"""Exact top-k by inner product with vector-approximation files.

Components become integers, then 8-bit cells of one width per dimension and block.  The blocks, each with its cells and its exact
vectors, are written once as a table.  For every query the cells give a lower and an upper bound on each inner product.
Candidates are taken in falling order of their upper bound and their exact product is read, until the k-th best exact product is
above every bound that is left.  A task carries each query's k-th best from block to block, so that later blocks read exact vectors
only where their bound is higher, and hands over k rows a query for all its blocks; a window keeps the best of all tasks.

Queries are dealt into chunks of about ``chunk_queries`` by the hash of their id; each chunk is broadcast (its
size is bounded by that number) and the table of blocks is passed once per chunk.

Vectors that are null, empty or hold null or non-finite components take no part, neither do rows with a null id.
Vectors of another length than the query's have no product with it.  A query meets every row but one that equals it in id
and vector (its own): rows that repeat an id are candidates and queries of their own, each with a ranking of its own
(told apart by ``query_no``).  An empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treeloom.llm.store import saved

CELLS = 256
#: Products of integers up to this stay exact in doubles.
EXACT = 2**53
_STEP = 64


def integer_vectors(ids: pa.Array, vectors: pa.Array, scale: int) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """By length: ids and the matrix of floor(scale * x) of the rows that take part."""
    out: dict[int, tuple[list, list]] = {}
    if isinstance(vectors, pa.ChunkedArray):
        vectors = vectors.combine_chunks()
    lengths = np.asarray(vectors.value_lengths().fill_null(0))
    offsets = np.asarray(vectors.offsets)
    flat = vectors.values.cast(pa.float64()).to_numpy(zero_copy_only=False)  # null components turn into nan
    key = np.asarray(ids.is_valid()) & (lengths > 0)
    numbers = np.asarray(ids.fill_null(0))
    for d in np.unique(lengths[key]):
        rows = np.nonzero(key & (lengths == d))[0]
        m = flat[offsets[rows][:, None] + np.arange(d)]
        fine = np.isfinite(m).all(axis=1)
        out[int(d)] = (numbers[rows[fine]], np.floor(m[fine] * scale))
    return out


class ApproximationFile:
    """One block of integer vectors with its cells."""

    def __init__(self, ids: np.ndarray, exact: np.ndarray, cells: np.ndarray | None = None):
        self.ids, self.exact = ids, exact
        self.low = exact.min(axis=0)
        self.width = np.floor((exact.max(axis=0) - self.low) / CELLS) + 1
        self.cells = np.minimum((exact - self.low) // self.width, CELLS - 1).astype(np.uint8) if cells is None else cells

    def best(self, query_ids: np.ndarray, queries: np.ndarray, k: int, least: np.ndarray) -> Iterator[tuple[int, list[tuple[int, int, bool]]]]:
        """(query, [(score, vector id, whether it equals the query in id and vector)]): rows that may be among a query's
        k best, given that k rows of ``least`` or more are known; ties go to the smaller id."""
        bound = self.exact.shape[1] * max(np.abs(self.exact).max(), 1) * max(np.abs(queries).max(), 1)
        whole = bound < EXACT
        corner = (queries * self.low).sum(axis=1)
        # cells in single precision: their rounding goes into the slack
        steps = queries * self.width
        base = (steps.astype(np.float32) @ self.cells.T.astype(np.float32)).astype(np.float64) + corner[:, None]
        slack = self.width - 1
        off = np.abs(steps).sum(axis=1) * (CELLS * 2.0**-22 * max(1, self.exact.shape[1] / 64)) + (0 if whole else bound * 1e-9)
        up = (np.maximum(queries, 0) * slack).sum(axis=1) + off
        down = (np.minimum(queries, 0) * slack).sum(axis=1) - off
        for j, qid in enumerate(query_ids):
            b = base[j]
            keep = min(k, len(b))
            floor_ = max(np.partition(b, len(b) - keep)[len(b) - keep] + down[j] if keep == k else -np.inf, least[j])
            rows = np.nonzero(b + up[j] >= floor_)[0]
            rows = rows[np.argsort(-b[rows], kind="stable")]
            found: list[tuple[int, int, bool]] = []
            for s in range(0, len(rows), _STEP):
                if len(found) >= k and b[rows[s]] + up[j] < -found[k - 1][0]:
                    break
                part = rows[s : s + _STEP]
                if whole:
                    scores = (self.exact[part] @ queries[j]).astype(np.int64).tolist()
                else:
                    q = [int(x) for x in queries[j]]
                    scores = [sum(int(x) * y for x, y in zip(self.exact[r], q)) for r in part]
                own = (self.ids[part] == qid) & (self.exact[part] == queries[j]).all(axis=1)
                found = sorted(found + [(-v, int(self.ids[r]), bool(o)) for v, r, o in zip(scores, part, own)])[:k]
            if found:
                yield j, [(-v, i, o) for v, i, o in found]


BLOCKS = "d int, n int, ids binary, cells binary, exact binary"


def approximation_table(vectors: DataFrame, scale: int, block_rows: int, id_col: str, vector_col: str) -> DataFrame:
    """Blocks of up to ``block_rows`` integer vectors of one length, with their cells."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for s in range(0, batch.num_rows, block_rows):
                part = batch.slice(s, block_rows)
                made = [(d, len(ids), ids.astype(np.int64).tobytes(), ApproximationFile(ids, m).cells.tobytes(), m.astype(np.float64).tobytes()) for d, (ids, m) in integer_vectors(part.column("id"), part.column("v"), scale).items() if len(ids)]
                if made:
                    kinds = (pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary())
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*made), kinds)], ["d", "n", "ids", "cells", "exact"])

    return vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).alias("v")).mapInArrow(run, BLOCKS)


def exact_top_k(vectors: DataFrame, queries: DataFrame, k: int = 10, scale: int = 1024, block_rows: int = 4096, chunk_queries: int = 16384, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, query_no, rank (from 1), vec_id, score for each row of ``queries`` against every row of ``vectors``.

    Scores must fit in 64 bits.
    """
    sc = vectors.sparkSession.sparkContext
    queries = queries.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).alias("v")).filter("id is not null and v is not null")
    n_chunks = max(1, math.ceil(queries.count() / chunk_queries))
    blocks = saved(approximation_table(vectors, scale, block_rows, id_col, vector_col), "cells")

    def scan(chunk: dict[int, tuple[np.ndarray, np.ndarray]]):
        held = sc.broadcast(chunk)
        want = k + 1  # the query's own row may be among them

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            best = {d: [[] for _ in ids] for d, (ids, _) in held.value.items()}
            least = {d: np.full(len(ids), -np.inf) for d, (ids, _) in held.value.items()}
            for batch in batches:
                for d, n, ids, cells, exact in zip(*(batch.column(c).to_pylist() for c in ("d", "n", "ids", "cells", "exact"))):
                    if d not in held.value:
                        continue
                    qids, q = held.value[d]
                    block = ApproximationFile(np.frombuffer(ids, np.int64), np.frombuffer(exact, np.float64).reshape(n, d), np.frombuffer(cells, np.uint8).reshape(n, d))
                    for t in range(0, len(qids), 512):
                        for j, found in block.best(qids[t : t + 512], q[t : t + 512], want, least[d][t : t + 512]):
                            mine = sorted(best[d][t + j] + found, key=lambda x: (-x[0], x[1]))[:want]
                            best[d][t + j] = mine
                            if len(mine) == want:
                                least[d][t + j] = mine[-1][0]
            for d, rows in best.items():
                ids = held.value[d][0]
                flat = [(int(ids[j]), j, i, v, o) for j, found in enumerate(rows) for v, i, o in found]
                for s in range(0, len(flat), 1 << 16):
                    cols = list(zip(*flat[s : s + (1 << 16)]))
                    yield pa.RecordBatch.from_arrays([*(pa.array(x, pa.int64()) for x in cols[:4]), pa.array(cols[4], pa.bool_())], ["query_id", "query_no", "vec_id", "score", "own"])

        return blocks.mapInArrow(run, "query_id long, query_no long, vec_id long, score long, own boolean")

    found = None
    for c in range(n_chunks):
        chunk = queries.filter(F.pmod(F.xxhash64("id"), F.lit(n_chunks)) == c) if n_chunks > 1 else queries
        table = chunk.toArrow()
        # queries of one id lie in one chunk: the number tells them apart
        part = scan(integer_vectors(table.column("id").combine_chunks(), table.column("v").combine_chunks(), scale) if table.num_rows else {})
        found = part if found is None else found.unionAll(part)
    query = ["query_id", "query_no"]
    order = Window.partitionBy(*query).orderBy(F.desc("score"), "vec_id", F.desc("own"))
    # one of the rows that equal the query is the query's own
    ranked = found.withColumn("at", F.row_number().over(order)).filter(F.col("at") <= k + 1)
    mine = ranked.withColumn("mine", F.min(F.when(F.col("own"), F.col("at"))).over(Window.partitionBy(*query)))
    ranks = F.col("at") - F.when(F.col("at") > F.col("mine"), 1).otherwise(0)
    return mine.filter("mine is null or at <> mine").withColumn("rank", ranks.cast("int")).filter(F.col("rank") <= k).select(*query, "rank", "vec_id", "score")
