"""Runs by array steps give the rows, and count the visits, of the runs from node to node."""

import random

import numpy as np

from tests.trees import random_path, random_tree
from treeloom.automaton.arrays import Forest, Scans
from treeloom.automaton.compile import to_automaton
from treeloom.automaton.evaluate import Counters, Document, Runner
from treeloom.automaton.jump import Jumper
from treeloom.tree.encode import flatten
from treeloom.xpath.parser import parse


def forest_of(rng):
    """Some trees side by side below node 1, as a document and as arrays."""
    rows, first = [], 2
    for _ in range(rng.randint(1, 4)):
        top = next((c for c in random_tree(rng, rng.randint(1, 25)).children if not isinstance(c, str)), None)
        if top is not None:
            rows += flatten(top, first=first, depth=2, parent=1)
            first = 2 + len(rows)
    num = [np.array([r[k] for r in rows], np.int64) for k in (0, 1, 3)]
    doc = Document(*num, [r[5] for r in rows], [r[6] for r in rows], [], 1)
    names = sorted({(r[6], r[5]) for r in rows})
    code = np.array([names.index((r[6], r[5])) for r in rows], np.int64)
    return doc, Forest.below(code, np.array(doc.above, np.int64), np.array(doc.after, np.int64), names)


def cases(seed, n):
    rng = random.Random(seed)
    while n:
        path = random_path(rng)
        a = to_automaton(parse(path))
        if Scans.fits(a):
            doc, forest = forest_of(rng)
            if doc.pre:
                states = frozenset(q for q, s in enumerate(a.states) if s.universal and rng.random() < 0.6) or a.top
                yield path, a, doc, forest, states
                n -= 1


def test_array_runs_agree_with_runs_from_match_to_match():
    for path, a, doc, forest, states in cases(41, 2500):
        run, want, got = Jumper(a), Counters(), Counters()
        filters = frozenset(q for q, s in enumerate(a.states) if not s.universal)
        held = run.forest(doc, filters, Counters())[1]
        rows = run.nodes_of(doc, run.forest(doc, states, want)[0])
        scans = Scans(a)
        scans.begin(forest)
        assert (scans.run(states, got) - 1).tolist() == rows, path
        assert scans.run(states).tolist() == [x + 1 for x in rows], path
        assert sorted(held) == scans.filters_held(), path
        if len(states) == 1:  # several states may ask one below the other
            assert (got.visited, got.marked) == (want.visited, want.marked), path


def test_array_runs_visit_what_runs_over_all_nodes_visit():
    for k, (path, a, doc, forest, states) in enumerate(cases(42, 2500)):
        early, lazy = bool(k & 1), bool(k & 2)
        run, want, got = Runner(a, early=early, lazy=lazy), Counters(), Counters()
        result = run.chain(doc, 0, states, want)
        rows = sorted({x for q, r in result.items() if a.states[q].universal for x in run.nodes_of(doc, r)})
        scans = Scans(a)
        scans.begin(forest)
        assert (scans.run(states) - 1).tolist() == rows, path
        scans.full_counters(states, early, lazy, got)
        assert (got.visited, got.marked) == (want.visited, want.marked), path
