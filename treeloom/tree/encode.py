"""Interval coding of trees: every node gets ``pre`` and ``last`` (document order, greatest ``pre`` below it).

A record is encoded on its own, with local numbers; a document that is larger than a task is made of many records
(fragments) under a few spine nodes, and its numbers are local ones plus the prefix sum of fragment sizes.  No window
ever runs over a whole document: fragments are summed per bucket of their order, buckets are summed on a table of
bounded size, and the rest happens inside a bucket.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

ROOT = "&"


@dataclass
class Node:
    """A tree under construction; children are nodes or texts."""

    label: str
    children: list[Node | str] = field(default_factory=list)
    attrs: dict[str, str] = field(default_factory=dict)


NODE_FIELDS = [
    ("pre", pa.int64(), "long"), ("last", pa.int64(), "long"), ("depth", pa.int32(), "int"), ("parent", pa.int64(), "long"), ("ord", pa.int32(), "int"),
    ("label", pa.string(), "string"), ("kind", pa.string(), "string"), ("host", pa.int64(), "long"), ("value", pa.string(), "string"),
]


def flatten(top: Node, first: int = 1, depth: int = 1, parent: int = 0, order: int = 1) -> list[list]:
    """Rows (pre, last, depth, parent, ord, label, kind, host, value) of a tree in document order; no recursion.

    ``host`` is the element that an attribute belongs to.  Empty texts are not stored.
    """
    rows: list[list] = []
    stack: list[tuple] = [(top, depth, parent, order, None)]
    while stack:
        item, d, up, o, host = stack.pop()
        if item is None:  # a subtree is complete
            rows[d][1] = first + len(rows) - 1
            continue
        pre = first + len(rows)
        if isinstance(item, str):
            rows.append([pre, pre, d, up, o, "#", "text", None, item])
            continue
        if isinstance(item, tuple):
            label, kind, below, value = item
            rows.append([pre, pre, d, up, o, label, kind, host, value])
        else:
            kind = "doc" if item.label == ROOT else "elem"
            below = [("@", "attrs", [(k, "attr", [("%", "value", [], v)], v) for k, v in item.attrs.items()], None)] if item.attrs else []
            below += [c for c in item.children if c != ""]
            rows.append([pre, pre, d, up, o, item.label, kind, None, None])
            host = pre
        stack.append((None, len(rows) - 1, 0, 0, None))
        stack.extend((c, d + 1, pre, k, host) for k, c in reversed(list(enumerate(below, 1))))
    return rows


#: Records that are taken out of a batch at a time, and nodes that a worker holds before it hands them on (and those of one record more).
SLICE_ROWS, BATCH_NODES = 256, 20_000


def encode_records(df: DataFrame, make: Callable[..., Node], columns: list[str], keys: list[str], depth: int = 1) -> DataFrame:
    """One row a node of the tree that ``make(*columns)`` builds of each row, with local numbers from 1 and the ``keys``."""
    kept = list(dict.fromkeys([*keys, *columns]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for s in range(0, batch.num_rows, SLICE_ROWS):
                part = batch.slice(s, SLICE_ROWS)
                owner: list[int] = []
                rows: list[list] = []
                for i, args in enumerate(zip(*(part.column(c).to_pylist() for c in columns))):
                    got = flatten(make(*args), depth=depth)
                    owner += [i] * len(got)
                    rows += got
                    if len(rows) >= BATCH_NODES or i == part.num_rows - 1:
                        cols = list(zip(*rows)) if rows else [[]] * len(NODE_FIELDS)
                        yield pa.RecordBatch.from_arrays([*(part.column(k).take(pa.array(owner, pa.int64())) for k in keys), *(pa.array(c, t) for c, (_, t, _) in zip(cols, NODE_FIELDS))], [*keys, *(n for n, _, _ in NODE_FIELDS)])
                        owner, rows = [], []

    schema = ", ".join([*(f"`{k}` {df.schema[k].dataType.simpleString()}" for k in keys), *(f"`{n}` {t}" for n, _, t in NODE_FIELDS)])
    return df.select(*kept).mapInArrow(run, schema)


# --- records of few shapes: outlined first, numbered by array steps when their places are known --------------------------


def outline(top: Node) -> tuple[str, list[str], int]:
    """The shape of a tree, which tells all its nodes but their texts, the texts of its attributes and leaves in document order, and
    how many rows ``flatten`` makes of it."""
    n = 0
    shape: list[str] = []
    texts: list[str] = []
    stack: list[Node | str | None] = [top]
    while stack:
        item = stack.pop()
        if item is None:
            shape.append(")")
            continue
        n += 1
        if isinstance(item, str):
            shape.append("#")
            texts.append(item)
        else:
            shape.append("(" + item.label)
            if item.attrs:
                n += 1 + 2 * len(item.attrs)
                shape += ["@" + k for k in item.attrs]
                texts += item.attrs.values()
            stack.append(None)
            stack += [c for c in reversed(item.children) if c != ""]
    return "\0".join(shape), texts, n


def _of_outline(shape: str) -> Node:
    """A tree of that shape, each text the number of its place among the texts."""
    n, open_ = 0, [Node("")]
    for token in shape.split("\0"):
        if token == ")":
            open_.pop()
        elif token == "#":
            open_[-1].children.append(str(n))
            n += 1
        elif token[0] == "@":
            open_[-1].attrs[token[1:]] = str(n)
            n += 1
        else:
            child = Node(token[1:])
            open_[-1].children.append(child)
            open_.append(child)
    return open_[0].children[0]


@dataclass
class _Template:
    """Columns of the rows of a shape, with numbers from 1 and 0 above the top; ``slot`` is the place of the text, or -1."""

    numbers: np.ndarray  # pre, last, depth, parent, ord, host (0: none), slot
    labels: list[str]
    kinds: list[str]

    @classmethod
    def of(cls, shape: str) -> _Template:
        rows = flatten(_of_outline(shape))
        numbers = np.array([(r[0], r[1], r[2], r[3], r[4], r[7] or 0, -1 if r[8] is None else int(r[8])) for r in rows], np.int64).T
        return cls(numbers, [r[5] for r in rows], [r[6] for r in rows])


#: Shapes that are kept, and characters of a shape that may be; longer ones are those of single documents.
KEPT_SHAPES, KEPT_CHARS = 4096, 2000
_kept_template = lru_cache(KEPT_SHAPES)(_Template.of)


def _template(shape: str) -> _Template:
    return _kept_template(shape) if len(shape) <= KEPT_CHARS else _Template.of(shape)


def _pylist(column: pa.Array) -> list:
    """As ``to_pylist``, which goes from element to element; lists and structs are taken column by column."""
    if pa.types.is_struct(column.type) and not column.null_count:
        names = [f.name for f in column.type]
        return [dict(zip(names, x)) for x in zip(*(_pylist(c) for c in column.flatten()))]
    if pa.types.is_list(column.type):
        at, valid = column.offsets.to_pylist(), column.is_valid().to_pylist()
        inner = _pylist(column.values.slice(at[0], at[-1] - at[0]))
        return [inner[x - at[0] : y - at[0]] if ok else None for x, y, ok in zip(at, at[1:], valid)]
    return column.to_pylist()


def _joined(texts: list[str], ends: list[int]) -> tuple[pa.Array, pa.Array]:
    """Of each record, whose texts end at ``ends``, the lengths as 32-bit numbers and their bytes, which are one value each and cheap to pass on."""
    _, offsets, data = pa.array(texts, pa.string()).buffers()
    at = np.frombuffer(offsets, np.int32, len(texts) + 1) if texts else np.zeros(1, np.int32)
    ends_at = np.array(ends, np.int32)
    binary = lambda stops, held: pa.Array.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer(stops.astype(np.int32)), held])
    return binary(4 * ends_at, pa.py_buffer(np.diff(at))), binary(at[ends_at], data if data is not None else pa.py_buffer(b""))


def _apart(lengths: pa.Array, texts: pa.Array) -> tuple[np.ndarray, pa.Array]:
    """Where the texts of each record begin among all of the batch, and these."""

    def whole(column: pa.Array) -> tuple[np.ndarray, pa.Buffer]:
        _, offsets, data = column.buffers()
        at = np.frombuffer(offsets, np.int32, len(column) + 1, 4 * column.offset)
        return at - at[0], data.slice(int(at[0]), int(at[-1] - at[0])) if data is not None else pa.py_buffer(b"")

    begins, sizes = whole(lengths)
    offsets = np.concatenate(([0], np.cumsum(np.frombuffer(sizes, np.int32), dtype=np.int64))).astype(np.int32)
    return begins // 4, pa.Array.from_buffers(pa.string(), len(offsets) - 1, [None, pa.py_buffer(offsets), whole(texts)[1]])


def outline_records(df: DataFrame, make: Callable[..., Node], columns: list[str], section: str, order: str) -> DataFrame:
    """section, order, shape and texts of the tree that ``make(*columns)`` builds of each row; ``part`` and ``at``: the task that the row fell to,
    in ``order`` within its section, and the nodes of the section before it there."""
    kept = list(dict.fromkeys([section, order, *columns]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        before: dict[str, int] = {}
        for batch in batches:
            for s in range(0, batch.num_rows, SLICE_ROWS):
                rows = batch.slice(s, SLICE_ROWS)
                shapes, texts, at, sizes, ends = [], [], [], [], [0]
                for name, args in zip(rows.column(section).to_pylist(), zip(*(_pylist(rows.column(c)) for c in columns))):
                    shape, own, n = outline(make(*args))
                    shapes.append(shape)
                    texts += own
                    ends.append(len(texts))
                    at.append(before.get(name, 0))
                    sizes.append(n)
                    before[name] = at[-1] + n
                some = [pa.array([part] * len(at), pa.int32()), pa.array(at, pa.int64()), pa.array(sizes, pa.int64()), pa.array(shapes, pa.string()), *_joined(texts, ends)]
                yield pa.RecordBatch.from_arrays([rows.column(section), rows.column(order), *some], [section, order, "part", "at", "size", "shape", "lengths", "texts"])

    dealt = df.select(*kept).repartitionByRange(section, order).sortWithinPartitions(section, order)
    return dealt.mapInArrow(run, f"`{section}` string, `{order}` long, part int, at long, size long, shape string, lengths binary, texts binary")


def number_records(df: DataFrame, keys: list[str]) -> DataFrame:
    """One row a node of outlined records with ``shift``, ``up`` (the node above the top) and ``depth``, with numbers after ``shift``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = np.cumsum(batch.column("size").to_numpy())
            x = 0
            while x < batch.num_rows:
                y = max(x + 1, int(np.searchsorted(sizes, (sizes[x - 1] if x else 0) + BATCH_NODES, "right")))
                yield _numbered(batch.slice(x, y - x), keys)
                x = y

    schema = ", ".join([*(f"`{k}` {df.schema[k].dataType.simpleString()}" for k in keys), *(f"`{n}` {t}" for n, _, t in NODE_FIELDS)])
    return df.select(*keys, "shift", "up", "depth", "size", "shape", "lengths", "texts").mapInArrow(run, schema)


def _numbered(batch: pa.RecordBatch, keys: list[str]) -> pa.RecordBatch:
    shapes = batch.column("shape").dictionary_encode()
    made = [_template(x) for x in shapes.dictionary.to_pylist()]
    which = shapes.indices.to_numpy()
    lengths = np.array([len(t.labels) for t in made])
    starts = np.cumsum(lengths) - lengths
    size = lengths[which]
    ends = np.cumsum(size)
    owner = np.repeat(np.arange(len(which)), size)
    row = np.arange(int(ends[-1])) - np.repeat(ends - size - starts[which], size)
    pre, last, depth, parent, order, host, slot = np.concatenate([t.numbers for t in made], axis=1)[:, row]
    shift, up, down = (batch.column(c).to_numpy()[owner] for c in ("shift", "up", "depth"))
    begins, texts = _apart(batch.column("lengths"), batch.column("texts"))
    text = begins[:-1][owner] + slot
    label, kind = (pa.array(x).dictionary_encode() for x in ([v for t in made for v in t.labels], [v for t in made for v in t.kinds]))
    columns = [
        pre + shift, last + shift, (depth + down - 1).astype(np.int32), np.where(parent == 0, up, parent + shift), order.astype(np.int32),
        label.dictionary.take(pa.array(label.indices.to_numpy()[row])), kind.dictionary.take(pa.array(kind.indices.to_numpy()[row])),
        pa.array(host + shift, pa.int64(), mask=host == 0), texts.take(pa.array(text, pa.int64(), mask=slot < 0)),
    ]
    arrays = [pa.array(c, t) if isinstance(c, np.ndarray) else c for c, (_, t, _) in zip(columns, NODE_FIELDS)]
    return pa.RecordBatch.from_arrays([*(batch.column(k).take(pa.array(owner)) for k in keys), *arrays], [*keys, *(n for n, _, _ in NODE_FIELDS)])


def offsets(sizes: DataFrame, group: list[str], order: Column, size: str, buckets: int = 256) -> DataFrame:
    """``sizes`` with ``offset``: the sum of ``size`` over rows of the same group that come earlier in ``order`` (a number from 0).

    Rows fall into ranges of their order; ranges are summed on a table of at most ``buckets`` rows a group.
    """
    rows = sizes.withColumn("__o", order.cast("long"))
    top = rows.agg(F.max("__o")).first()[0] or 0
    rows = rows.withColumn("__b", F.floor(F.col("__o") * F.lit(buckets) / F.lit(top + 1)).cast("int"))
    sums = rows.groupBy(*group, "__b").agg(F.sum(size).alias("__s"))
    before = sums.withColumn("__before", F.sum("__s").over(Window.partitionBy(*group).orderBy("__b")) - F.col("__s")).drop("__s")
    inside = F.sum(size).over(Window.partitionBy(*group, "__b").orderBy("__o")) - F.col(size)
    return rows.withColumn("__in", inside).join(before, [*group, "__b"]).withColumn("offset", F.col("__before") + F.col("__in")).drop("__o", "__b", "__in", "__before")
