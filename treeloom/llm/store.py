"""Intermediate tables in the folder that driver and executors share."""

from __future__ import annotations

import ctypes
import gc
import json
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from functools import wraps
from weakref import WeakKeyDictionary

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def checkpoint_root(spark: SparkSession) -> str:
    """The shared folder of ``spark.checkpoint.dir``; a folder of our own only in a local session where none is set (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    sc = spark.sparkContext
    if not sc.getCheckpointDir():
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="treeloom-checkpoint-"))
    return sc.getCheckpointDir().rstrip("/")


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``run`` for a worker that waits for its next task with little memory: what a task has freed goes back to the system.

    Spark keeps the workers of one task for the next ones, as many an executor as ever ran at a time."""

    @wraps(run)
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
            if trim is not None:  # not every C library has it
                trim(0)

    return work


#: Settings of the session: shuffle files go as soon as the query that wrote them has ended; the size up to which Spark gathers a table on
#: the driver to broadcast it, which it takes from the compressed files.
_CLEANUP, _BROADCAST = "spark.sql.classic.shuffleDependency.fileCleanup.enabled", "spark.sql.autoBroadcastJoinThreshold"
#: Files of narrow columns are many times larger in memory; keys that must be broadcast are so by name (``keyed_join``).
MAX_BROADCAST = 256 << 10


@contextmanager
def shuffles_removed(spark: SparkSession) -> Iterator[None]:
    """Also keeps tables that grow with the corpus off the driver."""
    before = {k: spark.conf.get(k, None) for k in (_CLEANUP, _BROADCAST)}
    spark.conf.set(_CLEANUP, "true")
    if spark._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold() > MAX_BROADCAST:
        spark.conf.set(_BROADCAST, str(MAX_BROADCAST))
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def saved(df: DataFrame, label: str, few_files: bool = False) -> DataFrame:
    """Writes ``df`` as Parquet into the shared folder and reads it back: lineage is cut, and a lost
    executor costs no recomputation of what lies before.  The shuffles behind it are not needed after that.

    ``few_files``: for narrow tables out of many small partitions, an eighth as many files, but one a core or more."""
    spark = df.sparkSession
    path = f"{checkpoint_root(spark)}/treeloom-{label}-{uuid.uuid4().hex}"
    if few_files:
        df = df.repartition(max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")) // 8))
    with shuffles_removed(spark):
        df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    _written[out] = path
    return out


#: Where the tables lie that ``saved`` has given and that are still in use.
_written: WeakKeyDictionary[DataFrame, str] = WeakKeyDictionary()


def discard(*tables: DataFrame) -> None:
    """Deletes tables that ``saved`` gave, once everything that reads them is saved itself."""
    for t in tables:
        path = _written.pop(t, None)
        if path is not None:
            jvm = t.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
            jvm.getFileSystem(t.sparkSession._jsc.hadoopConfiguration()).delete(jvm, True)


#: Keys that are broadcast as frequent ones, at most: each has more than this part of all rows.
HOT_KEYS = 1 << 14


def keyed_join(rows: DataFrame, keyed: DataFrame, on: list[str], n: str, total: int, how: str = "inner") -> DataFrame:
    """``rows`` joined with ``keyed``, which has each key once and in ``n`` the number of rows that have it, of ``total``.

    Keys with more than ``total / HOT_KEYS`` rows number fewer than ``HOT_KEYS``: these are broadcast, and their rows stay where they
    lie.  The rest is shuffled, at most that many rows a key.  Both tables are read twice, so give saved ones."""
    limit = total // HOT_KEYS
    hot = F.broadcast(keyed.filter(F.col(n) > limit).drop(n))
    cold = rows.join(F.broadcast(keyed.filter(F.col(n) > limit).select(*on)), on, "left_anti")
    return rows.join(hot, on, how).unionByName(cold.join(keyed.filter(F.col(n) <= limit).drop(n), on, how))


def fresh(columns: list[str], *names: str) -> list[str]:
    """``names``, each lengthened until no column has it in any case."""
    taken, out = {c.lower() for c in columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def row_identity(*columns: str) -> list[Column]:
    """Two 64-bit hashes with seeds of their own; together they tell rows apart by these columns."""
    parts = [x for c in columns for x in (F.col(f"`{c}`").isNull(), F.col(f"`{c}`"))]  # a null alone would leave no trace
    return [F.xxhash64(F.lit(seed), *parts) for seed in (1, 2)]


def literal_table(spark: SparkSession, schema: str, rows: list[tuple]) -> DataFrame:
    """A table of few rows that the plan itself carries: no Python runs on executors for it."""
    names = [x.split()[0] for x in schema.split(",")]
    text = json.dumps([dict(zip(names, r)) for r in rows])
    return spark.range(1).select(F.inline(F.from_json(F.lit(text), f"array<struct<{','.join(':'.join(x.split()) for x in schema.split(','))}>>")))
