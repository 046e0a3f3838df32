"""Index tables that are built once a session and folder, in the shared folder."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_built: dict[tuple[str, str, str], tuple[str, object]] = {}


#: Readers hold a row group at a time; by default its size is looked at after a hundred rows only.
WIDE_ROWS = {"parquet.block.size": str(16 << 20), "parquet.page.size.row.check.min": "1"}

#: Rows that make many more: small row groups, so that many tasks can read them.
NARROW_ROWS = {"parquet.block.size": str(4 << 20)}

#: A setting of the session: shuffle files go as soon as the query that wrote them has ended.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_SPLIT = "spark.sql.files.maxPartitionBytes"


def shared_root(spark: SparkSession) -> str:
    """Folder of ``spark.checkpoint.dir``; our own temporary one only where none is set."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    sc = spark.sparkContext
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="treeloom-checkpoint-"))
    return sc.getCheckpointDir().rstrip("/")


@contextmanager
def shuffles_dropped(spark: SparkSession, split: int | None = None) -> Iterator[None]:
    """Shuffle files go with the query that wrote them; ``split``: bytes of a file that a task reads at most."""
    wanted = {_CLEANUP: "true"} | ({_SPLIT: str(split)} if split else {})
    before = {k: spark.conf.get(k, None) for k in wanted}
    for k, v in wanted.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def is_built(spark: SparkSession, source: str, name: str) -> bool:
    return (spark.sparkContext.applicationId, source, name) in _built


def built_once(spark: SparkSession, source: str, name: str, build: Callable[[], DataFrame], sort: list[str] | None = None, wide: bool = False, narrow: bool = False, split: int | None = None) -> DataFrame:
    """The table ``name`` of ``source``, written as Parquet at first use in an application.  ``wide``: its rows hold megabytes; ``narrow``: each
    stands for many rows of what is made of it."""
    key = (spark.sparkContext.applicationId, source, name)
    if key not in _built:
        path = f"{shared_root(spark)}/treeloom-{name}-{uuid.uuid4().hex}"
        df = build()
        with shuffles_dropped(spark, split):
            (df.sortWithinPartitions(*sort) if sort else df).write.options(**(WIDE_ROWS if wide else NARROW_ROWS if narrow else {})).parquet(path)
        _built[key] = (path, df.schema)
    path, schema = _built[key]
    return spark.read.schema(schema).parquet(path)
