"""Runs of an automaton over one document held as arrays; explicit stacks, no recursion.

Options, all of which leave the answer as it is:

* ``memo``: transitions and asked states of (label, state set) are kept in tables shared by all documents of a task;
* ``early``: after the first-child tree, states whose truth is settled are not asked of the sibling tree;
* ``lazy``: a step that collects every node of a label below some node is answered by that node's interval.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from dataclasses import dataclass, field

import numpy as np

from treeloom.automaton.model import FALSE, TRUE, Automaton, atoms, conj, disj, neg

NOTHING: dict[int, tuple | None] = {}


class Document:
    """Nodes of one document in order; a contracted one holds a part of them, with the true parents."""

    def __init__(self, pre: np.ndarray, last: np.ndarray, parent: np.ndarray, label: list[str], kind: list[str], flags: list[list[bool]], up: int | None = None):
        """``up``: the node above all rows, if the rows are a fragment below it."""
        n = len(pre)
        self.up = up
        self.pre, self.last, self.label, self.kind, self.flags = pre.tolist(), last.tolist(), label, kind, flags
        after = np.searchsorted(pre, last, "right")
        index = np.arange(n)
        self.first = np.where(after > index + 1, index + 1, -1).tolist()
        above = np.full(n, -1, np.int64)
        stack: list[int] = []
        for i, p in enumerate(self.pre):
            while stack and self.last[stack[-1]] < p:
                stack.pop()
            above[i] = stack[-1] if stack else -1
            stack.append(i)
        self.above = above.tolist()
        limit = np.where(above >= 0, after[np.maximum(above, 0)], n)
        self.next = np.where(after < limit, after, -1).tolist()
        inside = parent == pre[np.maximum(above, 0)] if n else np.zeros(0, bool)
        self.child = np.where(above >= 0, inside, parent == up if up is not None else False).tolist()
        self.after = after.tolist()
        self._by_test: dict[object, list[int]] = {}

    def matching(self, guard) -> list[int]:
        """Positions of all nodes of a guard, in order."""
        got = self._by_test.get(guard)
        if got is None:
            got = self._by_test[guard] = [i for i, (k, x) in enumerate(zip(self.kind, self.label)) if guard.has(k, x)]
        return got


@dataclass
class Counters:
    visited: int = 0
    marked: int = 0


@dataclass
class Transition:
    rules: list[tuple[int, tuple | None, tuple]]
    left: frozenset[int]
    right: frozenset[int]
    later: dict[frozenset[int], frozenset[int]] = field(default_factory=dict)


def settled(f: tuple, true_left: frozenset[int]) -> tuple:
    """The formula once the first-child tree is known; predicates and marks stay open."""
    op = f[0]
    if op == "down" and f[1] == 1:
        return TRUE if f[2] in true_left else FALSE
    if op == "and":
        return conj(settled(f[1], true_left), settled(f[2], true_left))
    if op == "or":
        return disj(settled(f[1], true_left), settled(f[2], true_left))
    return neg(settled(f[1], true_left)) if op == "not" else f


class Runner:
    """Tables and options of a run; one for each task."""

    def __init__(self, automaton: Automaton, memo: bool = True, early: bool = True, lazy: bool = True):
        self.a, self.memo, self.early, self.lazy = automaton, memo, early, lazy
        self.table: dict[tuple, Transition] = {}
        self.bottom = automaton.bottom

    def transition(self, kind: str, label: str, child: bool, asked: frozenset[int]) -> Transition:
        key = (kind, label, child, asked)
        got = self.table.get(key) if self.memo else None
        if got is None:
            rules, left, right = [], frozenset(), frozenset()
            for q in asked:
                s = self.a.states[q]
                fits = s.guard.has(kind, label) and (child or s.axis != "child")
                loop = s.loop_at_attributes if kind == "attrs" else s.loop
                rules.append((q, s.match if fits else None, loop))
                for f in ([s.match] if fits else []) + [loop]:
                    left |= atoms(f, 1)
                    right |= atoms(f, 2)
            got = Transition(rules, left, right)
            if self.memo:
                self.table[key] = got
        return got

    def asked_later(self, t: Transition, left: dict[int, tuple | None]) -> frozenset[int]:
        """States that the sibling tree must still be asked for."""
        key = frozenset(left)
        got = t.later.get(key)
        if got is None:
            got = frozenset()
            for _, match, loop in t.rules:
                first = FALSE if match is None else settled(match, key)
                got |= atoms(first, 2)
                if first is not TRUE:  # else the loop is not needed any more
                    got |= atoms(settled(loop, key), 2)
            t.later[key] = got
        return got

    def value(self, f: tuple, i: int, left: dict, right: dict, doc: Document) -> tuple[bool, tuple | None]:
        """Truth of a formula at node i, and its marked nodes as a rope."""
        op = f[0]
        if op == "down":
            side = left if f[1] == 1 else right
            return (True, side[f[2]]) if f[2] in side else (False, None)
        if op == "and":
            a, x = self.value(f[1], i, left, right, doc)
            if not a:
                return False, None
            b, y = self.value(f[2], i, left, right, doc)
            return (True, (x, y) if x is not None and y is not None else x if y is None else y) if b else (False, None)
        if op == "or":
            a, x = self.value(f[1], i, left, right, doc)
            if a and x is None:
                return True, None
            b, y = self.value(f[2], i, left, right, doc)
            return a or b, (x, y) if x is not None and y is not None else x if y is None else y
        if op == "not":
            return not self.value(f[1], i, left, right, doc)[0], None
        if op == "mark":
            return True, ("node", i)
        if op == "pred":
            return bool(doc.flags[f[1]][i]), None
        return op == "true", None

    def run(self, doc: Document, counters: Counters) -> tuple | None:
        """The marked nodes of a run from the children of the document node (row 0)."""
        if not doc.pre:
            return None
        result = self.below(doc, 0, self.a.top, counters)
        return next((rope for q, rope in result.items() if q in self.a.top), None)

    def collecting(self, asked: frozenset[int]) -> int | None:
        if self.lazy and len(asked) == 1:
            (q,) = asked
            if self.a.states[q].collects:
                return q
        return None

    def below(self, doc: Document, at: int, asked: frozenset[int], counters: Counters) -> dict:
        if (q := self.collecting(asked)) is not None:
            counters.visited += 1
            return {q: ("lazy", at, q)}
        return self.chain(doc, doc.first[at], asked, counters)

    def chain(self, doc: Document, start: int, asked: frozenset[int], counters: Counters) -> dict:
        """States that hold at a node and its next siblings, each with its marked nodes."""
        frames: list[list] = [[start, asked, 0, None, None]]
        back: dict = NOTHING
        while frames:
            frame = frames[-1]
            i, want, phase, left, t = frame
            if phase == 0:
                if i < 0:
                    back = {q: None for q in want if q in self.bottom}
                    frames.pop()
                    continue
                counters.visited += 1
                frame[4] = t = self.transition(doc.kind[i], doc.label[i], doc.child[i], want)
                frame[2] = 1
                if t.left:
                    if (q := self.collecting(t.left)) is not None:
                        back = {q: ("lazy", i, q)}
                    else:
                        frames.append([doc.first[i], t.left, 0, None, None])
                        continue
                else:
                    back = NOTHING
                frame = frames[-1]
                frame[3] = back
                phase = 1
            if phase == 1:
                if frame[3] is None:
                    frame[3] = back
                frame[2] = 2
                right = self.asked_later(t, frame[3]) if self.early else t.right
                if right:
                    frames.append([doc.next[i], right, 0, None, None])
                    continue
                back = NOTHING
            back = self.holding(t, i, frame[3], back, doc, counters)
            frames.pop()
        return back

    def holding(self, t: Transition, i: int, left: dict, right: dict, doc: Document, counters: Counters) -> dict:
        """Of the states of a transition those that hold at node i, each with its marked nodes."""
        out: dict = {}
        for q, match, loop in t.rules:
            if match is not None:
                ok, rope = self.value(match, i, left, right, doc)
                if ok:
                    if rope is not None:
                        counters.marked += 1
                    out[q] = rope
                    continue
            ok, rope = self.value(loop, i, left, right, doc)
            if ok:
                out[q] = rope
        return out

    def nodes_of(self, doc: Document, rope: tuple | None) -> list[int]:
        """Positions in the document, in order, each once."""
        found: list[int] = []
        stack = [rope] if rope is not None else []
        while stack:
            x = stack.pop()
            if x[0] == "node":
                found.append(x[1])
            elif x[0] == "lazy":
                hits = doc.matching(self.a.states[x[2]].guard)
                found += hits[bisect_right(hits, x[1]) : bisect_left(hits, doc.after[x[1]])]
            else:
                stack += [y for y in x if y is not None]
        return sorted(set(found))

    def count(self, doc: Document, rope: tuple | None) -> int:
        return len(self.nodes_of(doc, rope))


class AllStates(Runner):
    """The plain bottom-up run: all states at all nodes, from the last to the first.  Nodes times states; what the others are held against."""

    def run(self, doc: Document, counters: Counters) -> tuple | None:
        if not doc.pre:
            return None
        empty: dict = {q: None for q in self.bottom}
        everyone = frozenset(range(len(self.a.states)))
        held: list[dict] = [empty] * len(doc.pre)
        at = lambda i: held[i] if i >= 0 else empty
        for i in range(len(doc.pre) - 1, 0, -1):
            counters.visited += 1
            t = self.transition(doc.kind[i], doc.label[i], doc.child[i], everyone)
            held[i] = self.holding(t, i, at(doc.first[i]), at(doc.next[i]), doc, counters)
        return next((rope for q, rope in at(doc.first[0]).items() if q in self.a.top), None)
