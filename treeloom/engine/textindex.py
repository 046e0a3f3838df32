"""The text index of a tree: shards over its own texts that know, for every text, the nodes above it.

A text predicate gives texts; the rows of the index hold their nodes and the labels and intervals of all their ancestors, so that a
path whose only condition is that predicate can be answered from the matches upward, without reading a node: the labels above a
match decide which ancestors are results, once for each distinct row of labels, and ancestors that several matches share are merged
in the task that holds the shard.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treeloom.text.fm import PatternError, TextIndex
from treeloom.text.shards import one_by_one
from treeloom.xpath.ast import Exists, Path, Step, ValuePred

#: Bytes of text in a shard; production shards hold 32 MB and more.
SHARD_BYTES = 1 << 20
SAMPLE = 16
#: Between the labels of a row of ancestors; no name holds it.
_BAR = "\x1f"
KEYS = pa.schema(
    [("doc", pa.int64()), ("frag", pa.int64()), ("pre", pa.int64()), ("parent", pa.int64()), ("label", pa.string()), ("kind", pa.string()), ("host", pa.int64()), ("path", pa.string()), ("pres", pa.list_(pa.int64())), ("lasts", pa.list_(pa.int64()))]
)
SHARDS = "n_texts long, n_bytes long, sample int, data binary, keys binary"


def build_tree_index(nodes: DataFrame, spine: list[tuple], shard_bytes: int = SHARD_BYTES, sample: int = SAMPLE) -> DataFrame:
    """Shards of the texts and attribute values of ``nodes`` (with values); ``spine``: (doc, pre, last, label) of nodes above all fragments."""
    above = sorted(spine)
    cols = ["doc", "frag", "pre", "last", "parent", "label", "kind", "host", "value"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        texts: list[bytes] = []
        size = 0
        stack: list[tuple] = []
        unit: tuple | None = None

        def shard() -> pa.RecordBatch:
            keys = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), KEYS.types)], schema=KEYS)
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, KEYS) as out:
                out.write_batch(keys)
            ix = TextIndex.build(texts, sample, "blocks")
            values = (len(texts), ix.n, sample, ix.pack(), sink.getvalue().to_pybytes())
            kinds = (pa.int64(), pa.int64(), pa.int32(), pa.binary(), pa.binary())
            return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(values, kinds)], ["n_texts", "n_bytes", "sample", "data", "keys"])

        for batch in batches:
            for doc, frag, pre, last, parent, label, kind, host, value in zip(*(batch.column(c).to_pylist() for c in cols)):
                if (doc, frag) != unit:
                    unit = (doc, frag)
                    stack = [(p, end, name) for d, p, end, name in above if d == doc and p <= pre <= end] if above else []
                while stack and stack[-1][1] < pre:
                    stack.pop()
                if kind in ("text", "attr") and value is not None and "\0" not in value:
                    if texts and size + len(value) > shard_bytes:
                        yield shard()
                        rows, texts, size = [], [], 0
                    own = [s for s in stack if s[1] >= last]
                    rows.append((doc, frag, pre, parent, label, kind, host, _BAR.join(s[2] for s in own), [s[0] for s in own], [s[1] for s in own]))
                    texts.append(value.encode("utf-8", "surrogatepass"))
                    size += len(texts[-1]) + 1
                stack.append((pre, last, label))
        if texts:
            yield shard()

    # the leaf below an attribute repeats its value and is above nothing
    dealt = nodes.select(*cols).filter("frag <> -1 and kind <> 'value'").repartition("doc", "frag").sortWithinPartitions("doc", "pre")
    return dealt.mapInArrow(run, SHARDS)


_ASK: dict[str, Callable[[TextIndex, str], np.ndarray]] = {
    "contains": TextIndex.contains, "starts-with": TextIndex.starts_with, "ends-with": TextIndex.ends_with, "=": TextIndex.equals,
    "<": lambda ix, p: ix.compare("<", p), "<=": lambda ix, p: ix.compare("<=", p), ">": lambda ix, p: ix.compare(">", p), ">=": lambda ix, p: ix.compare(">=", p),
}


def indexable(kind: str, word: str) -> bool:
    try:
        TextIndex.symbols(word)
    except PatternError:
        return False
    return kind in _ASK


def _keys(data: bytes) -> pa.Table:
    return pa.ipc.open_stream(data).read_all()


def count_hits(index: DataFrame, kind: str, word: str) -> tuple[int, int, int]:
    """(occurrences of the word, bytes of all texts, sampling step): one backward search a shard, nothing is located."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for (data,) in one_by_one(batch, "data"):
                ix = TextIndex.unpack(data)
                low, high = ix.search(word) if kind == "contains" else (0, len(_ASK[kind](ix, word)))
                found.append(high - low)
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.int64()), batch.column("n_bytes"), batch.column("sample")], ["o", "b", "s"])

    r = index.select("data", "n_bytes", "sample").mapInArrow(run, "o long, b long, s int").agg(F.sum("o"), F.sum("b"), F.max("s")).first()
    return r[0] or 0, r[1] or 0, r[2] or 1


def search_texts(index: DataFrame, kind: str, word: str) -> DataFrame:
    """doc, frag, pre, parent, label, kind, host of the texts and attribute values that satisfy the predicate."""
    out = ["doc", "frag", "pre", "parent", "label", "kind", "host"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data, keys in one_by_one(batch, "data", "keys"):
                hits = _ASK[kind](TextIndex.unpack(data), word)
                if len(hits):
                    yield from _keys(keys).select(out).take(pa.array(hits)).combine_chunks().to_batches()

    return index.select("data", "keys").mapInArrow(run, "doc long, frag long, pre long, parent long, label string, kind string, host long")


# --- from the matches upward


def chain_of(path: Path) -> tuple[tuple[Step, ...], tuple[Step, ...], ValuePred] | None:
    """(steps of the path, steps of its filter, predicate) if the last step's chain of filters is the path's only condition."""
    if not path.absolute or not path.steps or any(s.filters for s in path.steps[:-1]) or len(path.steps[-1].filters) != 1:
        return None
    down: list[Step] = []
    f = path.steps[-1].filters[0]
    while isinstance(f, (Exists, ValuePred)):
        steps = f.path.steps
        inner = [g for s in steps for g in s.filters]
        down += [Step(s.axis, s.test) for s in steps if not (s.axis == "self" and s.test == "node()")]
        if isinstance(f, ValuePred):
            every = [*path.steps, *down]
            ok = not inner and all(s.axis in ("child", "descendant") for s in path.steps) and all(s.axis in ("child", "descendant", "attribute") for s in every)
            return (tuple(Step(s.axis, s.test) for s in path.steps), tuple(down), f) if ok else None
        if len(inner) != 1 or not steps[-1].filters:
            return None
        f = inner[0]
    return None


def _onward(labels: list[str], at: int, step: Step) -> list[int]:
    """Positions on a row of labels, from the document node to a match, that a step leads to; the last may be text or attribute."""
    n = len(labels)
    if step.axis == "attribute":
        ok = at + 2 == n - 1 and labels[at + 1] == "@" and (step.test in ("*", "node()") or labels[at + 2] == step.test)
        return [n - 1] if ok else []
    # what lies below an attribute node is no element
    last = labels.index("@") if "@" in labels else n
    to = range(at + 1, min(last, n if step.axis == "descendant" else at + 2))
    text = [i for i in to if labels[i] == "#"]
    elem = [i for i in to if labels[i] != "#"]
    if step.test == "text()":
        return text
    if step.test == "node()":
        return elem + text
    return elem if step.test == "*" else [i for i in elem if labels[i] == step.test]


def results_above(labels: list[str], main: tuple[Step, ...], down: tuple[Step, ...]) -> list[int]:
    """Positions of the result nodes above a match whose row of labels is given, the match's own last."""
    here = {0}
    for step in main:
        here = {j for i in here for j in _onward(labels, i, step)}
    # an element's value are its own texts; a text or attribute is its own value
    end = len(labels) - 1
    goals = {end} if labels[-1] != "#" else {end, end - 1}
    out = []
    for i in here:
        there = {i}
        for step in down:
            there = {k for j in there for k in _onward(labels, j, step)}
        if there & goals:
            out.append(i)
    return sorted(out)


def climb(index: DataFrame, path: Path) -> DataFrame:
    """doc, pre, last of the results of a path that :func:`chain_of` takes apart."""
    main, down, pred = chain_of(path)
    kind, word = pred.kind, pred.word

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        where: dict[tuple[str, str, str], list[int]] = {}
        for batch in batches:
            for data, raw in one_by_one(batch, "data", "keys"):
                hits = _ASK[kind](TextIndex.unpack(data), word)
                if not len(hits):
                    continue
                t = _keys(raw).take(pa.array(hits))
                merged: dict[tuple[int, int], int] = {}
                cols = [t.column(c).to_pylist() for c in ("doc", "pre", "label", "kind", "path", "pres", "lasts")]
                for doc, pre, label, what, path_, pres, lasts in zip(*cols):
                    key = (path_, label, what)
                    got = where.get(key)
                    if got is None:
                        got = where[key] = results_above([*path_.split(_BAR), "#" if what == "text" else label], main, down)
                    for i in got:
                        merged[doc, pres[i] if i < len(pres) else pre] = lasts[i] if i < len(lasts) else pre + (what == "attr")
                if merged:
                    docs, nodes = zip(*merged)
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (docs, nodes, list(merged.values()))], ["doc", "pre", "last"])

    # a document, or a fragment, lies in few shards: what tasks share is little
    return index.select("data", "keys").mapInArrow(run, "doc long, pre long, last long").distinct()
