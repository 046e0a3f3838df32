"""Runs that go from one match of a state to the next by label positions, never over the nodes between.

A state of the main path holds on any tree, so its answer below a node is the union, over its matches there, of what the match
leads to; a filter state holds below a node if some match there holds.  Both only need the sorted positions of each label.  Where a
match hands over to a state that looks at its whole subtree, matches inside that subtree add nothing and are jumped over as one.
What the last step collects stays a range of positions until nodes are asked for, and is counted as one.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right, insort

from treeloom.automaton.evaluate import Counters, Document
from treeloom.automaton.model import Automaton


class Found:
    """Nodes that a run has marked: ranges of the positions of each state's label, and single nodes."""

    def __init__(self) -> None:
        self.ranges: dict[int, list[tuple[int, int]]] = {}
        self.nodes: list[int] = []


def _parts(f: tuple) -> list[tuple]:
    return _parts(f[1]) + _parts(f[2]) if f[0] == "and" else [f]


class Jumper:
    """One for each task; the automaton must have no steps to siblings."""

    def __init__(self, automaton: Automaton):
        self.a = automaton
        #: per main state: what its match asks of the node, and the states that it hands over to
        self.asks: dict[int, list[tuple]] = {}
        self.goes: dict[int, list[int]] = {}
        for q, s in enumerate(automaton.states):
            if s.universal:
                parts = [f for f in _parts(s.match) if f not in (("down", 1, q), ("down", 2, q)) and f[0] != "true"]
                onward = [f for f in parts if f[0] == "down" and automaton.states[f[2]].universal]
                self.goes[q] = [f[2] for f in onward]
                self.asks[q] = [f for f in parts if f not in onward and f[0] != "mark"]  # by value: formulas come to workers as copies

    @staticmethod
    def fits(automaton: Automaton) -> bool:
        return all(s.axis in ("child", "descendant") or s.guard.kinds == frozenset(("attr",)) for s in automaton.states)

    def run(self, doc: Document, counters: Counters) -> Found:
        """The answer from the children of the document node (row 0)."""
        self._begin(doc, counters)
        if doc.pre:
            for q in self.a.top:
                self._collect(q, 0)
        return self.found

    def forest(self, doc: Document, states: frozenset[int], counters: Counters) -> tuple[Found, list[int]]:
        """The answer of main states, and the filter states that hold, over rows that all lie below ``doc.up``."""
        self._begin(doc, counters)
        held = []
        for q in states:
            if self.a.states[q].universal:
                self._collect(q, -1)
            elif self._any(q, -1):
                held.append(q)
        return self.found, held

    def _begin(self, doc: Document, counters: Counters) -> None:
        self.doc, self.counters, self.found = doc, counters, Found()
        self.known: dict[tuple[int, int], bool] = {}
        #: per state, the (first row, end) of what has been collected below some node
        self.done: dict[int, list[tuple[int, int]]] = {}

    def _hits(self, q: int, at: int) -> tuple[list[int], int, int]:
        hits = self.doc.matching(self.a.states[q].guard)
        return hits, bisect_right(hits, at), len(hits) if at < 0 else bisect_left(hits, self.doc.after[at])

    def _children(self, q: int, at: int):
        """Matches of a child step (or of attributes, which lie below their holder's attribute node)."""
        hits, x, y = self._hits(q, at)
        doc = self.doc
        while x < y:
            i = hits[x]
            if doc.above[i] == at and doc.child[i]:
                yield i
                x += 1
                continue
            # the child of ``at`` that i lies below has no other match of its own level inside
            while doc.above[i] != at:
                i = doc.above[i]
            x = bisect_left(hits, doc.after[i], x) if doc.after[i] > hits[x] else x + 1

    def _collect(self, q: int, at: int) -> None:
        s = self.a.states[q]
        below = s.axis == "descendant"
        if below:
            end = len(self.doc.pre) if at < 0 else self.doc.after[at]
            done = self.done.setdefault(q, [])
            k = bisect_right(done, (at, end)) - 1
            if k >= 0 and done[k][1] >= end:
                return  # an outer node has asked the same
            insort(done, (at, end))
        if s.collects:
            self.counters.visited += 1
            _, x, y = self._hits(q, at)
            if y > x:
                self.found.ranges.setdefault(q, []).append((x, y))
            return
        if not below:
            for i in self._children(q, at):
                self._match(q, i)
            return
        hits, x, y = self._hits(q, at)
        whole = bool(self.goes[q]) and all(self.a.states[r].axis == "descendant" for r in self.goes[q])
        while x < y:
            i = hits[x]
            held = self._match(q, i)
            x = bisect_left(hits, self.doc.after[i], x) if held and whole else x + 1

    def _match(self, q: int, i: int) -> bool:
        self.counters.visited += 1
        if not all(self._holds(f, i) for f in self.asks[q]):
            return False
        self.counters.marked += not self.goes[q]
        if not self.goes[q]:
            self.found.nodes.append(i)
        for r in self.goes[q]:
            self._collect(r, i)
        return True

    def _holds(self, f: tuple, i: int) -> bool:
        op = f[0]
        if op == "down":
            return self._any(f[2], i)
        if op == "and":
            return self._holds(f[1], i) and self._holds(f[2], i)
        if op == "or":
            return self._holds(f[1], i) or self._holds(f[2], i)
        if op == "not":
            return not self._holds(f[1], i)
        if op == "pred":
            return bool(self.doc.flags[f[1]][i])
        return op == "true"

    def _any(self, q: int, at: int) -> bool:
        s = self.a.states[q]
        if s.axis == "descendant":
            hits, x, y = self._hits(q, at)
            if s.match[0] == "true":
                self.counters.visited += x < y
                return x < y
            return any(self._known(q, hits[k]) for k in range(x, y))
        return any(self._known(q, i) for i in self._children(q, at))

    def _known(self, q: int, i: int) -> bool:
        got = self.known.get((q, i))
        if got is None:
            self.counters.visited += 1
            # what the loop carries on over siblings is what the positions stand for
            parts = [f for f in _choices(self.a.states[q].match) if f not in (("down", 1, q), ("down", 2, q))]
            got = self.known[q, i] = any(self._holds(f, i) for f in parts)
        return got

    # --- answers

    def _ranges(self, found: Found) -> dict[int, list[list[int]]]:
        out = {}
        for q, spans in found.ranges.items():
            merged: list[list[int]] = []
            for x, y in sorted(spans):
                if merged and x <= merged[-1][1]:
                    merged[-1][1] = max(merged[-1][1], y)
                else:
                    merged.append([x, y])
            out[q] = merged
        return out

    def count(self, doc: Document, found: Found) -> int:
        return len(set(found.nodes)) + sum(y - x for spans in self._ranges(found).values() for x, y in spans)

    def nodes_of(self, doc: Document, found: Found) -> list[int]:
        out = set(found.nodes)
        for q, spans in self._ranges(found).items():
            hits = doc.matching(self.a.states[q].guard)
            for x, y in spans:
                out.update(hits[x:y])
        return sorted(out)


def _choices(f: tuple) -> list[tuple]:
    return _choices(f[1]) + _choices(f[2]) if f[0] == "or" else [f]
