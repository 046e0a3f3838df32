"""Fragments of spined documents packed as arrays: one row a forest, written once a tree and read by every run by array steps.

A run from node to node deals out, sorts and turns into Python all rows of the tree at every pass.  Packed, a pass is a scan of ten
bytes a node, and the tree is dealt out once.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from treeloom.automaton.arrays import Forest, Scans
from treeloom.automaton.evaluate import Counters
from treeloom.automaton.model import Automaton, LabelSet
from treeloom.sources.store import built_once, is_built
from treeloom.sources.trees import Tree

#: Rows of neighbouring fragments that make up one forest, about.
PACKED_ROWS = 50_000
#: ``code``, ``above`` and ``after`` are 32-bit numbers, ``pre`` 64-bit ones; tops have -1 above them.
PACKED = "doc long, up long, n int, kinds array<string>, labels array<string>, code binary, above binary, after binary, pre binary"
#: The markup of a forest as bytes, and where in it that of each row begins and ends, as 32-bit numbers.
MARKUP = "begin binary, end binary, markup binary"
#: Of forests that lack rows below others, the greatest number below each row, as 64-bit numbers.
LAST = "last binary"
#: Bytes of markup that a worker hands on at a time, and those of one result more.
BATCH_BYTES = 4 << 20


def packed(tree: Tree, spine: list[tuple[int, int]], markup: bool = False) -> DataFrame:
    """Forests of the tree below its ``spine``, the (doc, pre) of the nodes above all fragments; with their ``markup`` in a table of its own."""
    if not tree.name:
        return _packed(tree, spine, markup)
    if not markup and is_built(tree.spark, tree.source, f"{tree.name}-markup"):
        markup = True  # its table has the same forests, and columns that are not asked for are not read
    return built_once(tree.spark, tree.source, f"{tree.name}-markup" if markup else f"{tree.name}-forests", lambda: _packed(tree, spine, markup), wide=True)


def marked_up(t: pa.Table, after: np.ndarray) -> tuple[np.ndarray, np.ndarray, bytes]:
    """(begin, end, markup) of rows of one forest in document order, as ``serialize.markup_events`` has it.

    Every row opens and closes once; ``after`` and the depths give the places of both, so that all pieces are put in order by one ``take``.
    """
    n, rows = t.num_rows, np.arange(t.num_rows)
    kind, label, value = (t.column(c).combine_chunks() for c in ("kind", "label", "value"))
    elem, attr, text = (pc.equal(kind, k).to_numpy(zero_copy_only=False) for k in ("elem", "attr", "text"))
    pre, host = t.column("pre").to_numpy(), pc.fill_null(t.column("host"), -1).to_numpy()
    hosts = host[attr]
    closes = np.zeros(n, bool)  # attributes that end the tag of their element
    closes[attr] = np.append(hosts[1:] != hosts[:-1], True)[: len(hosts)]
    bare = elem & ~np.isin(pre, hosts)
    escaped = pc.replace_substring(pc.replace_substring(pc.replace_substring(value, "&", "&amp;"), "<", "&lt;"), ">", "&gt;")
    quoted = pc.replace_substring(escaped, '"', "&quot;")
    join, end = pc.binary_join_element_wise, pa.array([">" if x else "" for x in (bare | closes).tolist()])
    opening = pc.choose(
        pa.array(elem * 1 + attr * 2 + text * 3), pa.array([""] * n), join("<", label, end, ""),
        join(pc.fill_null(join(" ", label, '="', quoted, '"', ""), ""), end, ""), pc.fill_null(escaped, ""),
    )
    closing = pc.if_else(pa.array(elem), join("</", label, ">", ""), "")
    depth = t.column("depth").to_numpy()
    opens = 2 * rows - (depth - depth[0])
    shuts = opens + 2 * (after - rows) - 1
    order = np.empty(2 * n, np.int64)
    order[opens], order[shuts] = rows, rows + n
    pieces = pa.concat_arrays([opening, closing])
    pieces = pieces.take(pa.array(order))
    _, offsets, data = pieces.buffers()
    at = np.frombuffer(offsets, np.int32, 2 * n + 1, 4 * pieces.offset)
    return at[opens] - at[0], at[shuts + 1] - at[0], data.slice(int(at[0]), int(at[-1] - at[0])).to_pybytes() if data is not None else b""


def _packed(tree: Tree, spine: list[tuple[int, int]], markup: bool = False) -> DataFrame:
    return packed_rows(tree.all.filter("frag <> -1"), spine, markup)


def packed_rows(nodes: DataFrame, spine: list[tuple[int, int]], markup: bool = False, lasts: bool = False) -> DataFrame:
    """Forests of nodes of fragments, with each of which come those above it; with ``lasts`` what lies below may be missing."""
    schema = ", ".join([PACKED, *([MARKUP] if markup else []), *([LAST] if lasts else [])])
    over: dict[int, list[int]] = {}
    for doc, pre in spine:
        over.setdefault(doc, []).append(pre)
    above_all = {doc: np.array(sorted(pres), np.int64) for doc, pres in over.items()}

    def pack(t: pa.Table) -> pa.RecordBatch:
        pre, last, parent = (t.column(c).to_numpy() for c in ("pre", "last", "parent"))
        kind, label = (t.column(c).combine_chunks().dictionary_encode() for c in ("kind", "label"))
        kinds, labels = kind.dictionary.to_pylist(), label.dictionary.to_pylist()
        both = kind.indices.to_numpy().astype(np.int64) * len(labels) + label.indices.to_numpy()
        used, code = np.unique(both, return_inverse=True)
        at = np.searchsorted(pre, parent)
        inside = pre[np.minimum(at, len(pre) - 1)] == parent
        arrays = (code, np.where(inside, at, -1), np.searchsorted(pre, last, "right"))
        row = [t.column("doc")[0].as_py(), int(parent[0]), len(pre), [kinds[x // len(labels)] for x in used], [labels[x % len(labels)] for x in used], *(x.astype(np.int32).tobytes() for x in arrays), pre.astype(np.int64).tobytes()]
        if markup:
            begin, end, data = marked_up(t, arrays[2])
            row += [begin.tobytes(), end.tobytes(), data]
        if lasts:
            row.append(last.astype(np.int64).tobytes())
        types = [pa.int64(), pa.int64(), pa.int32(), pa.list_(pa.string()), pa.list_(pa.string()), *[pa.binary()] * 7]
        return pa.RecordBatch.from_arrays([pa.array([x], y) for x, y in zip(row, types)], [x.split()[0] for x in schema.split(", ")])

    def heads(t: pa.Table) -> np.ndarray:
        """Where a forest may begin: the tops of fragments, by the spine node over each."""
        doc, parent = t.column("doc").to_numpy(), t.column("parent").to_numpy()
        top = np.zeros(len(doc), bool)
        for d in np.unique(doc):
            pres, mine = above_all.get(int(d), np.zeros(0, np.int64)), doc == d
            top |= mine & np.isin(parent, pres)
        return np.nonzero(top)[0]

    def cut(t: pa.Table, end: bool) -> tuple[list[pa.Table], pa.Table | None]:
        at = heads(t)
        doc, parent = t.column("doc").to_numpy()[at], t.column("parent").to_numpy()[at]
        out, begin = [], 0
        for k in [*(np.nonzero((doc[1:] != doc[:-1]) | (parent[1:] != parent[:-1]))[0] + 1).tolist(), len(at)]:
            stop = t.num_rows if k == len(at) else int(at[k])
            while stop - begin > PACKED_ROWS:
                far = at[np.searchsorted(at, begin + PACKED_ROWS)] if at[-1] >= begin + PACKED_ROWS else stop
                if far >= stop:
                    break
                out.append(t.slice(begin, int(far) - begin))
                begin = int(far)
            if k == len(at) and not end:  # what comes next may belong to it
                return out, t.slice(begin)
            out.append(t.slice(begin, stop - begin))
            begin = stop
        return out, None

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        rows = 0
        for batch in batches:
            if batch.num_rows:
                held.append(batch)
                rows += batch.num_rows
            if rows > 2 * PACKED_ROWS:
                whole, rest = cut(pa.Table.from_batches(held).combine_chunks(), False)
                yield from map(pack, whole)
                held = rest.to_batches()
                rows = rest.num_rows
        if rows:
            yield from map(pack, cut(pa.Table.from_batches(held).combine_chunks(), True)[0])

    rows = nodes.select("doc", "frag", "pre", "last", "parent", "label", "kind", *(["depth", "host", "value"] if markup else []))
    return rows.repartition("doc", "frag").sortWithinPartitions("doc", "pre").drop("frag").mapInArrow(work, schema)


def _strings(begin: np.ndarray, end: np.ndarray, data: memoryview) -> pa.Array:
    offsets = np.concatenate(([0], np.cumsum(end - begin))).astype(np.int32)
    whole = b"".join([data[x:y] for x, y in zip(begin.tolist(), end.tolist())])
    return pa.Array.from_buffers(pa.string(), len(begin), [None, pa.py_buffer(offsets), pa.py_buffer(whole)])


def run_packed(
    forests: DataFrame, a: Automaton, what: str, schema: str, asked: dict[tuple[int, int], frozenset[int]] | None, options: dict,
    over: dict[tuple[int, int], tuple[int, list[int]]] | None = None, seeds: LabelSet | None = None,
) -> DataFrame:
    """``what`` of each forest: the filter "states" that hold, or of the main states that are ``asked`` there the "nodes", "count", "counters"
    or "markup"; this also of the fragments that are parts of results ``over`` them, given with the depth of the spine node.
    With ``seeds`` a run for "nodes" sees these and what lies above them only."""

    def in_markup(doc: int, up: int, v: dict, forest: Forest, scans: Scans) -> Iterator[pa.RecordBatch]:
        begin, end, numbers = (np.frombuffer(v[c].as_buffer(), t) for c, t in (("begin", np.int32), ("end", np.int32), ("pre", np.int64)))
        data = memoryview(v["markup"].as_buffer())
        whole = np.array([k in ("elem", "text") for k, _ in forest.names], bool)  # attributes are parts of a tag
        states = asked.get((doc, up), frozenset())
        found = scans.run(states) - 1 if states else np.zeros(0, np.int64)
        found = found[whole[forest.code[found + 1]]]
        depth, results = over.get((doc, up), (0, []))
        tops = np.nonzero((forest.above[1:] == 0) & whole[forest.code[1:]])[0] if results else np.zeros(0, np.int64)
        for rows, pre, at in [(found, numbers[found], np.zeros(len(found), np.int64)), *((tops, np.full(len(tops), r), 2 * numbers[tops] - depth - 1) for r in results)]:
            sums = np.cumsum(end[rows] - begin[rows], dtype=np.int64)
            x = 0
            while x < len(rows):
                y = max(x + 1, int(np.searchsorted(sums, (sums[x - 1] if x else 0) + BATCH_BYTES, "right")))
                some = rows[x:y]
                cols = [pa.array(np.full(len(some), doc, np.int64)), pa.array(pre[x:y], pa.int64()), pa.array(at[x:y], pa.int64()), _strings(begin[some], end[some], data)]
                yield pa.RecordBatch.from_arrays(cols, names)
                x = y

    def one(doc: int, up: int, forest: Forest, pre: bytes | None, last: bytes | None, scans: Scans) -> list[list]:
        kept = None
        if seeds is not None:
            forest, kept = forest.up_from(forest.hits(seeds))
        scans.begin(forest)
        if what == "states":
            held = scans.filters_held()
            return [[doc] * len(held), [up] * len(held), held]
        states, counters = asked.get((doc, up), frozenset()), Counters()
        found = scans.run(states, counters if what == "counters" and not options else None)
        if what == "nodes":
            numbers = np.frombuffer(pre, np.int64)
            if kept is not None:
                at = kept[found] - 1
                return [np.full(len(found), doc, np.int64), numbers[at], np.frombuffer(last, np.int64)[at]]
            return [np.full(len(found), doc, np.int64), numbers[found - 1], numbers[forest.after[found] - 2]]
        if what == "count":
            return [[len(found)]]
        read = forest.n - 1
        if options:
            scans.full_counters(states, options["early"], options["lazy"], counters)
        elif a.can_jump:
            read = len(np.unique(np.concatenate([forest.hits(g) for g in a.relevant()])))
        return [[x] for x in (doc, read, counters.visited, counters.marked, len(found))]

    names = [x.split()[0] for x in schema.split(", ")]
    types = [pa.int32() if x.endswith(" int") else pa.int64() for x in schema.split(", ")]
    cols = ["doc", "up", "kinds", "labels", "code", "above", "after", *{"nodes": ["pre"] if seeds is None else ["pre", "last"], "markup": ["pre", "begin", "end", "markup"]}.get(what, [])]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scans = Scans(a)
        for batch in batches:
            for i in range(batch.num_rows):
                v = {c: batch.column(c)[i] for c in cols}
                doc, up = v["doc"].as_py(), v["up"].as_py()
                if asked is not None and what != "counters" and not asked.get((doc, up)) and (doc, up) not in (over or ()):
                    continue
                code, above, after = (np.frombuffer(v[c].as_buffer(), np.int32) for c in ("code", "above", "after"))
                forest = Forest.below(code, above, after, list(zip(v["kinds"].as_py(), v["labels"].as_py())))
                if what == "markup":
                    scans.begin(forest)
                    yield from in_markup(doc, up, v, forest, scans)
                    continue
                got = one(doc, up, forest, *(v[c].as_buffer() if c in v else None for c in ("pre", "last")), scans)
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(got, types)], names)

    return forests.select(*cols).mapInArrow(work, schema)
