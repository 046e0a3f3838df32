"""Automaton runs on a cluster: each document is run in one task, over the rows that matter to the automaton.

``jump`` keeps nodes of relevant labels only; the filter is on columns and reaches the Parquet scan, so that the
contracted tree is all that is shuffled; the run itself then goes from match to match (``Jumper``).  Text predicates are answered once
for all documents and come as flags.  A document with a spine is larger than a task and is run fragment by fragment.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treeloom.automaton.arrays import Scans
from treeloom.automaton.compile import Unsupported, guard_of, to_automaton
from treeloom.automaton.evaluate import AllStates, Counters, Document, Runner
from treeloom.automaton.jump import Jumper
from treeloom.automaton.model import MARK, Automaton, atoms, has_pred
from treeloom.engine.columnar import KEY, Columnar, above_any
from treeloom.engine.forests import packed, packed_rows, run_packed
from treeloom.engine.textindex import chain_of, climb
from treeloom.sources.trees import Tree
from treeloom.xpath.ast import Exists, Filter, Path, Step, ValuePred
from treeloom.xpath.parser import parse


def pred_hits(tree: Tree, p: ValuePred) -> DataFrame:
    """(doc, pre) of nodes that satisfy a value predicate at the end of its path."""
    col = Columnar(tree)
    step = p.path.steps[-1]
    if step.axis == "self":
        return col.valued(p).unionAll(tree.matching(p.kind, p.word).select(*KEY))
    return col.hits(step, p).select(*KEY)


def restricted(tree: Tree, a: Automaton) -> DataFrame:
    """Nodes of labels on which the automaton does more than loop, and the document nodes."""
    per_kind: dict[str, set[str]] = {}
    for g in a.relevant():
        for k in g.kinds:
            per_kind.setdefault(k, set()).update(g.names)
    tests = [(F.col("kind") == k) & F.col("label").isin(sorted(names)) for k, names in per_kind.items()]
    return tree.nodes.filter(reduce(lambda x, y: x | y, tests, F.col("kind") == "doc"))


#: Option of the plain bottom-up run.
ALL_STATES = {"all_states": True}
#: Rows of neighbouring fragments that a task runs as one forest, about.
FOREST_ROWS = 200_000


def _run(nodes: DataFrame, a: Automaton, flags: list[DataFrame], emit: Callable, schema: str, options: dict, spine: _Spine | None = None, ask: Callable | None = None) -> DataFrame:
    """One run a document, or, with a ``spine``, one for neighbouring fragments below one node of it, whose states ``ask(doc, spine
    node)`` gives.  Without ``options`` the run jumps, if the automaton lets it."""
    cols = ["doc", "frag", "pre", "last", "parent", "label", "kind"]
    unit = ["doc"] if spine is None else ["doc", "frag"]
    rows = nodes.select(*cols)
    for k, hits in enumerate(flags):
        rows = rows.join(hits.distinct().withColumn(f"p{k}", F.lit(True)), KEY, "left")
    names = [f"p{k}" for k in range(len(flags))]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if options == ALL_STATES:
            runner = AllStates(a)
        else:
            runner = Jumper(a) if not options and Jumper.fits(a) else Runner(a, **options)
        held: pa.Table | None = None

        def one(t: pa.Table) -> pa.RecordBatch:
            num = [t.column(c).to_numpy() for c in ("pre", "last", "parent")]
            own = t.column("doc")[0].as_py()
            up = spine.over(own, int(num[0][0])) if spine is not None else None
            doc = Document(*num, t.column("label").to_pylist(), t.column("kind").to_pylist(), [t.column(n).to_pylist() for n in names], up)
            counters = Counters()
            if spine is None:
                return emit(own, doc, runner, runner.run(doc, counters), counters)
            states = ask(own, up) or frozenset()
            if isinstance(runner, Jumper):
                marked, result = runner.forest(doc, states, counters)
                return emit(own, doc, runner, result if emit is _emit_states else marked, counters)
            result = runner.chain(doc, 0, states, counters) if states else {}
            if emit is _emit_states:
                return emit(own, doc, runner, [q for q in result if not a.states[q].universal], counters)
            ropes = [r for q, r in result.items() if r is not None and a.states[q].universal]
            return emit(own, doc, runner, tuple(ropes) if len(ropes) > 1 else ropes[0] if ropes else None, counters)

        def cuts(t: pa.Table) -> list[int]:
            other = np.zeros(t.num_rows - 1, bool)
            for c in unit:
                ids = t.column(c).to_numpy()
                other |= ids[1:] != ids[:-1]
            heads = [0, *(np.nonzero(other)[0] + 1).tolist()]
            if spine is None:
                return heads
            docs, pre = t.column("doc").to_numpy(), t.column("pre").to_numpy()
            out, last = [], None
            for h in heads:
                here = (int(docs[h]), spine.over(int(docs[h]), int(pre[h])))
                if here != last or h - out[-1] > FOREST_ROWS:
                    out.append(h)
                    last = here
            return out

        for batch in batches:
            if not batch.num_rows:
                continue
            t = pa.Table.from_batches([batch])
            t = t if held is None else pa.concat_tables([held, t])
            at = cuts(t)
            for s, e in zip(at, at[1:]):
                yield one(t.slice(s, e - s))
            held = t.slice(at[-1])
        if held is not None:
            yield one(held)

    return rows.repartition(*unit).sortWithinPartitions("doc", "pre").mapInArrow(work, schema)


def _emit_nodes(doc_id: int, doc: Document, runner: Runner, rope: tuple | None, counters: Counters) -> pa.RecordBatch:
    at = runner.nodes_of(doc, rope)
    return pa.RecordBatch.from_pydict({"doc": pa.array([doc_id] * len(at), pa.int64()), "pre": pa.array([doc.pre[i] for i in at], pa.int64()), "last": pa.array([doc.last[i] for i in at], pa.int64())})


def _emit_counters(doc_id: int, doc: Document, runner: Runner, rope: tuple | None, counters: Counters) -> pa.RecordBatch:
    row = (doc_id, len(doc.pre), counters.visited, counters.marked, runner.count(doc, rope))
    return pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in row], ["doc", "rows", "visited", "marked", "results"])


_NODES = "doc long, pre long, last long"
_COUNTERS = "doc long, rows long, visited long, marked long, results long"


def _plan(tree: Tree, path: Path | str, jump: bool, pairs: set[tuple[str, str, str]] | None = None) -> tuple[DataFrame, Automaton, list[DataFrame]]:
    a = to_automaton(parse(path) if isinstance(path, str) else path, pairs)
    nodes = restricted(tree, a) if jump and a.can_jump else tree.nodes
    return nodes, a, [pred_hits(tree, p) for p in a.preds]


def run_all_states(tree: Tree, path: Path | str) -> DataFrame:
    """The same results from the plain bottom-up run: every state at every node.  For documents without a spine."""
    if tree.spined:
        raise Unsupported("a document with a spine is larger than a task")
    nodes, a, flags = _plan(tree, path, False)
    return _run(nodes, a, flags, _emit_nodes, _NODES, ALL_STATES)


def _options(jump: bool, memo: bool, early: bool, lazy: bool) -> dict:
    """None of them for a run from match to match, which has no transitions to memoise."""
    return {} if jump and memo and early and lazy else {"memo": memo, "early": early, "lazy": lazy}


def run_top_down(tree: Tree, path: Path | str, jump: bool = True, memo: bool = True, early: bool = True, lazy: bool = True, pairs: set[tuple[str, str, str]] | None = None) -> DataFrame:
    """doc, pre, last of the results of a top-down run; ``pairs`` of labels make hopeless filters constants."""
    nodes, a, flags = _plan(tree, path, jump, pairs)
    if _by_arrays(tree, a, memo, early, lazy):
        return _array_runs(tree, a, "nodes", _NODES, _options(jump, memo, early, lazy))
    if tree.spined and crosses_no_fragment(a):
        return _fragments(tree, nodes, a, flags, _emit_nodes, _NODES, _options(jump, memo, early, lazy))
    return _run(nodes, a, flags, _emit_nodes, _NODES, _options(jump, memo, early, lazy))


def count_top_down(tree: Tree, path: Path | str, jump: bool = True, memo: bool = True, early: bool = True, lazy: bool = True, pairs: set[tuple[str, str, str]] | None = None) -> DataFrame:
    """n: the number of results of the same run, counted where they are found."""
    a = to_automaton(parse(path) if isinstance(path, str) else path, pairs)
    if not _by_arrays(tree, a, memo, early, lazy):
        return run_top_down(tree, path, jump, memo, early, lazy, pairs).agg(F.count("*").alias("n"))
    return _array_runs(tree, a, "count", "n long", _options(jump, memo, early, lazy)).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))


def goes_by_arrays(tree: Tree, path: Path | str) -> bool:
    """Whether top-down runs of the path are array steps over packed forests."""
    return _by_arrays(tree, to_automaton(parse(path) if isinstance(path, str) else path))


def markup_top_down(tree: Tree, path: Path | str, pairs: set[tuple[str, str, str]] | None = None) -> DataFrame:
    """doc, pre, at, xml of the results of the same run, cut out of the markup that is packed with the forests.

    A result in a fragment is one row (``at`` 0).  One above all fragments may be as large as the document: it comes in the pieces that
    its part of the spine and the fragments below it are, in the order of ``at``.
    """
    a = to_automaton(parse(path) if isinstance(path, str) else path, pairs)
    if not _by_arrays(tree, a):
        raise Unsupported("markup is packed for runs by array steps only")
    return _array_runs(tree, a, "markup", "doc long, pre long, at long, xml string", {})


def pack_markup(tree: Tree) -> None:
    """Packs a spined tree with its markup, for runs of all modes; where it is packed without, that table is used beside."""
    if tree.spined:
        packed(tree, _spine_of(tree, []).keys, markup=True)


def visits(tree: Tree, path: Path | str, jump: bool = True, memo: bool = True, early: bool = True, lazy: bool = True, pairs: set[tuple[str, str, str]] | None = None) -> DataFrame:
    """doc, rows read, nodes visited, marked and returned by the same run, one row a document or piece of it."""
    nodes, a, flags = _plan(tree, path, jump, pairs)
    if _by_arrays(tree, a, memo, early, lazy):
        return _array_runs(tree, a, "counters", _COUNTERS, _options(jump, memo, early, lazy))
    if tree.spined and crosses_no_fragment(a):
        return _fragments(tree, nodes, a, flags, _emit_counters, _COUNTERS, _options(jump, memo, early, lazy))
    return _run(nodes, a, flags, _emit_counters, _COUNTERS, _options(jump, memo, early, lazy))


def _chain(filters: list[Filter]) -> ValuePred | None:
    """The predicate at the end of a chain of single filters without negation or choice."""
    if len(filters) != 1 or not isinstance(filters[0], (Exists, ValuePred)):
        return None
    inner = [f for s in filters[0].path.steps for f in s.filters]
    if isinstance(filters[0], ValuePred):
        return None if inner else filters[0]
    return _chain(inner)


#: Spine nodes that reach the driver at most.
MAX_SPINE = 100_000


class _Spine:
    """The nodes above all fragments, in order, and the innermost one over a position."""

    def __init__(self, rows: list[tuple]):
        self.rows = sorted(rows)
        self.keys = [(r[0], r[1]) for r in self.rows]
        self.index = {k: i for i, k in enumerate(self.keys)}

    def over(self, doc: int, pre: int) -> int:
        i = bisect_left(self.keys, (doc, pre)) - 1
        while self.rows[i][2] < pre:
            i = self.index[doc, self.rows[i][3]]
        return self.rows[i][1]


def crosses_no_fragment(a: Automaton) -> bool:
    """Steps to siblings would tie fragments to each other."""
    return not any((atoms(s.match, 2) | atoms(s.loop, 2)) - {q} for q, s in enumerate(a.states))


def run_fragments(tree: Tree, path: Path | str, jump: bool = True) -> DataFrame:
    """doc, pre, last of the results, for documents that are larger than a task.

    Filter states are asked of every fragment first and come up as one bit set a spine node.  The spine, which is small, is
    then evaluated on the driver, which tells the main states that reach the fragments below each of its nodes; a
    second pass runs these.  Steps to siblings are not supported here.
    """
    nodes, a, flags = _plan(tree, path, jump)
    if not crosses_no_fragment(a):
        raise Unsupported("steps to siblings cross fragments")
    if _by_arrays(tree, a):
        return _array_runs(tree, a, "nodes", _NODES, _options(jump, True, True, True))
    return _fragments(tree, nodes, a, flags, _emit_nodes, _NODES, {} if jump else {"lazy": True})


def _fragments(tree: Tree, nodes: DataFrame, a: Automaton, flags: list[DataFrame], emit: Callable, schema: str, options: dict) -> DataFrame:
    spine = _spine_of(tree, flags)
    pieces = nodes.filter("frag <> -1")
    filters = frozenset(q for q, s in enumerate(a.states) if not s.universal)
    below: dict[tuple[int, int], set[int]] = {k: set() for k in spine.keys}
    if filters:
        masks = _run(pieces, a, flags, _emit_states, "doc long, up long, state int", options and {**options, "lazy": False}, spine, lambda doc, up: filters).distinct()
        for r in masks.collect():  # at most spine nodes times states
            below[r["doc"], r["up"]].add(r["state"])
    asked, found = _down_the_spine(a, spine, below)
    wanted = {k: v for k, v in asked.items() if v}
    got = _run(pieces, a, flags, emit, schema, options, spine, lambda doc, up: wanted.get((doc, up)))
    return got.unionAll(tree.spark.createDataFrame(_of_the_spine(spine, asked, found, emit is _emit_counters), schema))


def _of_the_spine(spine: _Spine, asked: dict, found: list[tuple], counters: bool) -> list[tuple]:
    if not counters:
        return found
    return [(spine.rows[0][0], len(spine.rows), len(asked), len(found), len(found))] if spine.rows else []


#: Spines by built tree.
_spines: dict[tuple, _Spine] = {}


def _spine_of(tree: Tree, flags: list[DataFrame]) -> _Spine:
    """The spine with a flag a predicate; without flags it is read once a tree that is kept under a name."""
    key = (tree.spark.sparkContext.applicationId, tree.source, tree.name)
    if not flags and tree.name and key in _spines:
        return _spines[key]
    rows = tree.nodes.filter("frag = -1").select("doc", "pre", "last", "parent", "label", "kind")
    for k, hits in enumerate(flags):
        rows = rows.join(hits.distinct().withColumn(f"p{k}", F.lit(True)), KEY, "left")
    spine_rows = [tuple(r) for r in rows.limit(MAX_SPINE + 1).collect()]
    if len(spine_rows) > MAX_SPINE:
        raise Unsupported("the spine is too large for the driver")
    spine = _Spine(spine_rows)
    if not flags and tree.name:
        _spines[key] = spine
    return spine


def _by_arrays(tree: Tree, a: Automaton, memo: bool = True, early: bool = True, lazy: bool = True) -> bool:
    """Whether a run goes by array steps over packed forests; runs that leave out single options go from node to node, as these
    are what they compare."""
    return tree.spined and memo == early == lazy and Scans.fits(a)


def _array_runs(tree: Tree, a: Automaton, what: str, schema: str, options: dict) -> DataFrame:
    """As ``_fragments``, over packed forests: "nodes", "count" or "counters" of the results."""
    spine = _spine_of(tree, [])
    forests = packed(tree, spine.keys)
    below: dict[tuple[int, int], set[int]] = {k: set() for k in spine.keys}
    if not all(s.universal for s in a.states):
        for r in run_packed(forests, a, "states", "doc long, up long, state int", None, options).distinct().collect():  # at most spine nodes times states
            below[r["doc"], r["up"]].add(r["state"])
    asked, found = _down_the_spine(a, spine, below)
    states = {k: frozenset(v) for k, v in asked.items() if v}
    if what == "markup":
        from treeloom.engine.serialize import spine_pieces

        over = _results_over(spine, {(doc, pre) for doc, pre, _ in found})
        got = run_packed(packed(tree, spine.keys, markup=True), a, what, schema, states, options, {k: v for k, v in over.items() if v[1]})
        return got.unionAll(spine_pieces(tree, found)) if found else got
    got = run_packed(forests, a, what, schema, states, options)
    more = [(len(found),)] if what == "count" else _of_the_spine(spine, asked, found, what == "counters")
    return got.unionAll(tree.spark.createDataFrame(more, schema))


def _results_over(spine: _Spine, found: set[tuple[int, int]]) -> dict[tuple[int, int], tuple[int, list[int]]]:
    """Of each spine node its depth, and the results among it and the nodes above it."""
    out: dict[tuple[int, int], tuple[int, list[int]]] = {}
    for doc, pre, _, parent, *_ in spine.rows:
        depth, above = out.get((doc, parent), (0, []))
        out[doc, pre] = (depth + 1, [*above, pre] if (doc, pre) in found else above)
    return out


def _down_the_spine(a: Automaton, spine: _Spine, below: dict[tuple[int, int], set[int]]) -> tuple[dict, list[tuple]]:
    """The main states that reach the fragments below each spine node, and the results among the spine nodes."""
    truth, asked, found = _up_the_spine(a, spine, below), {}, []
    for doc, pre, last, parent, label, kind, *flag in spine.rows:
        here = frozenset(a.top) if kind == "doc" else frozenset()
        for q in asked.get((doc, parent), ()):
            s = a.states[q]
            ok = s.guard.has(kind, label) and _local(s.match, truth[doc, pre], flag)
            if ok and _marks(s.match):
                found.append((doc, pre, last))
            here |= atoms(s.match if ok else s.loop, 1) & a.bottom
        asked[doc, pre] = here
    return asked, found


def _marks(f: tuple) -> bool:
    return f is MARK or f[0] == "and" and (_marks(f[1]) or _marks(f[2]))


def _local(f: tuple, below: set[int], flag: list) -> bool:
    """Truth of a formula at a spine node; what lies beside it is asked elsewhere."""
    op = f[0]
    if op == "down":
        return f[1] == 2 or f[2] in below
    if op in ("and", "or"):
        x, y = _local(f[1], below, flag), _local(f[2], below, flag)
        return (x and y) if op == "and" else (x or y)
    if op == "not":
        return not _local(f[1], below, flag)
    return bool(flag[f[1]]) if op == "pred" else op in ("true", "mark")


def _up_the_spine(a: Automaton, spine: _Spine, below: dict[tuple[int, int], set[int]]) -> dict[tuple[int, int], set[int]]:
    """States that hold somewhere among the children of each spine node."""
    for doc, pre, _, parent, label, kind, *flag in reversed(spine.rows):
        own = below[doc, pre]
        own |= a.bottom
        for q, s in enumerate(a.states):
            if s.universal or (doc, parent) not in below:
                continue
            deeper = s.axis == "descendant" and q in own and kind != "attrs"
            if deeper or s.guard.has(kind, label) and _local(s.match, own, flag):
                below[doc, parent].add(q)
    return below


def _emit_states(doc_id: int, doc: Document, runner: Runner | Jumper, held: list[int], counters: Counters) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([doc_id] * len(held), pa.int64()), pa.array([doc.up] * len(held), pa.int64()), pa.array(held, pa.int32())], ["doc", "up", "state"])


def seed_of(path: Path) -> ValuePred | None:
    """The value predicate that a bottom-up run can start from: the only condition of the path, and positive."""
    return _chain([f for s in path.steps for f in s.filters])


def can_run_bottom_up(path: Path) -> bool:
    """A missing match must never make the path hold: one positive predicate, on the last step, or no filter at all."""
    plain = all(s.axis in ("child", "descendant", "attribute", "self") for s in path.steps)
    inner = any(s.filters for s in path.steps[:-1])
    return plain and not inner and (seed_of(path) is not None or not path.steps[-1].filters)


#: Seeds whose fragments are told to all tasks at most.
FEW_SEEDS = 10_000


def _no_leaves(nodes: DataFrame, kinds: frozenset[str]) -> DataFrame:
    """Nodes that are or lie above nodes of ``kinds``: of other kinds than these, texts, attributes and their values lie above none."""
    return nodes.filter(F.col("kind").isin(sorted(kinds | {"doc", "elem"} | ({"attrs"} if "attr" in kinds else set()))))


def near_seeds(tree: Tree, seeds: DataFrame, kinds: frozenset[str] | None = None) -> DataFrame:
    """The seeds and their ancestors: of the nodes only fragments that hold a seed are kept before any is shuffled, and the spine.

    With the ``kinds`` of the seeds given, nodes that cannot lie above one are not read."""
    nodes = tree.nodes if kinds is None else _no_leaves(tree.nodes, kinds)
    units = seeds.select("doc", "frag").distinct()
    local = nodes.join(units, ["doc", "frag"], "left_semi")
    if tree.spined:
        local = local.filter("frag <> -1").unionByName(nodes.filter("frag = -1").join(units.select("doc").distinct(), "doc", "left_semi"))
    return above_any(local, seeds, or_self=True)


def _arrays_up(tree: Tree, a: Automaton, step: Step) -> DataFrame:
    """Results of a path without filters in a spined document, upward from the nodes of its last step, by array steps.

    Rows that can be seeds or lie above one are dealt out by fragment and packed; a task cuts each forest down to its seeds and what lies above
    them, and runs that.  Paths whose seeds are of the same kind deal out the same rows, which is done once in a query that unites them.
    """
    spine = _spine_of(tree, [])
    asked, found = _down_the_spine(a, spine, {k: set() for k in spine.keys})
    guard = guard_of(step)
    seeds = Columnar(tree).candidates(step).filter("frag <> -1")
    rows = _no_leaves(tree.nodes.filter("frag <> -1"), guard.kinds)
    if seeds.limit(FEW_SEEDS + 1).count() <= FEW_SEEDS:
        rows = rows.join(F.broadcast(seeds.select("doc", "frag").distinct()), ["doc", "frag"], "left_semi")
    states = {k: frozenset(v) for k, v in asked.items() if v}
    got = run_packed(packed_rows(rows, spine.keys, lasts=True), a, "nodes", _NODES, states, {}, seeds=guard)
    return got.unionAll(tree.spark.createDataFrame(found, _NODES))


def _asking(a: Automaton) -> tuple[Column, frozenset[str]]:
    """Nodes at which a predicate is asked, and their kinds."""
    guards = [s.guard for s in a.states if has_pred(s.match)]
    one = lambda g: F.col("kind").isin(sorted(g.kinds)) & (~F.col("label").isin(sorted(g.names)) if g.rest else F.col("label").isin(sorted(g.names)))
    return reduce(lambda x, y: x | y, map(one, guards), F.lit(False)), frozenset().union(*(g.kinds for g in guards))


def run_bottom_up(tree: Tree, path: Path | str, counters: bool = False) -> DataFrame:
    """The same results from the matches upward: only seeds and their ancestors are read, each ancestor once.

    Seeds are the nodes whose text satisfies the path's predicate, or, without one, the nodes of its last label.  If the text index
    has the matches, it also has their ancestors, and no node is read at all (``climb``).  A document with a spine is run fragment by
    fragment.
    """
    path = parse(path) if isinstance(path, str) else path
    if not can_run_bottom_up(path):
        raise ValueError("a bottom-up run needs a single positive predicate on its last step, or none")
    a = to_automaton(path)
    seed = seed_of(path)
    if seed is not None and not counters and chain_of(path) is not None and tree.by_index(seed.kind, seed.word):
        return climb(tree.index, path)
    if seed is not None:
        flags = [pred_hits(tree, p) for p in a.preds]
        asking, kinds = _asking(a)
        seeds = tree.nodes.filter(asking).join(flags[0], KEY, "left_semi")
    elif _by_arrays(tree, a) and not counters:
        return _arrays_up(tree, a, path.steps[-1])
    else:
        flags, kinds = [], guard_of(path.steps[-1]).kinds
        seeds = Columnar(tree).candidates(path.steps[-1])
    emit, schema = (_emit_counters, _COUNTERS) if counters else (_emit_nodes, _NODES)
    options = {"memo": True, "early": True, "lazy": False}
    if tree.spined and crosses_no_fragment(a):
        return _fragments(tree, near_seeds(tree, seeds, kinds), a, flags, emit, schema, options)
    return _run(near_seeds(tree, seeds, kinds), a, flags, emit, schema, options)
