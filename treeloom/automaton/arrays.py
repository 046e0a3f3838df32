"""Runs of an automaton over a whole forest by array steps: no loop over nodes, one pass of a few numpy calls a state.

Filter states are settled first, from the innermost outwards (a scan upward); the main states then go down from where they are asked.  Row 0 stands
for what lies above the forest.  The answers and the counters are those of ``Jumper`` (``run``) and
of ``Runner`` (``full_counters``); steps to siblings and text predicates are left to these.
"""

from __future__ import annotations

import numpy as np

from treeloom.automaton.evaluate import Counters
from treeloom.automaton.model import Automaton, LabelSet


class Forest:
    """Rows of a forest in document order below row 0; ``code`` points into ``names``, the (kind, label) that occur."""

    def __init__(self, code: np.ndarray, above: np.ndarray, after: np.ndarray, names: list[tuple[str, str]]):
        self.code, self.above, self.after, self.names, self.n = code, above, after, names, len(code)
        self._hits: dict[LabelSet, np.ndarray] = {}
        self._order: np.ndarray | None = None
        self._levels: list[np.ndarray] | None = None

    @classmethod
    def below(cls, code: np.ndarray, above: np.ndarray, after: np.ndarray, names: list[tuple[str, str]]) -> Forest:
        """Of rows whose tops have -1 above them; a row 0 of no label is put before them."""
        return cls(np.concatenate(([len(names)], code)), np.concatenate(([-1], above + 1)), np.concatenate(([len(code) + 1], after + 1)), [*names, ("doc", "")])

    def hits(self, guard: LabelSet) -> np.ndarray:
        """Rows of a guard, in order."""
        got = self._hits.get(guard)
        if got is None:
            fits = np.array([guard.has(k, x) for k, x in self.names], bool)
            fits_row = fits[self.code]
            fits_row[0] = False
            got = self._hits[guard] = np.nonzero(fits_row)[0]
        return got

    def mask(self, rows: np.ndarray) -> np.ndarray:
        out = np.zeros(self.n, bool)
        out[rows] = True
        return out

    def cover(self, rows: np.ndarray) -> np.ndarray:
        """Whether a row lies strictly below one of ``rows``."""
        steps = np.zeros(self.n + 1, np.int32)
        np.add.at(steps, rows + 1, 1)
        np.subtract.at(steps, self.after[rows], 1)
        return np.cumsum(steps[: self.n]) > 0

    def up_from(self, rows: np.ndarray) -> tuple[Forest, np.ndarray]:
        """The forest of ``rows`` and of what lies above them, and the row that each of its rows is here."""
        sums = np.concatenate(([0], np.cumsum(self.mask(rows))))
        keep = sums[self.after] > sums[:-1]
        keep[0] = True
        kept, place = np.nonzero(keep)[0], np.concatenate(([0], np.cumsum(keep)))
        above = self.above[kept]
        return Forest(self.code[kept], np.where(above < 0, -1, place[above]), place[self.after[kept]], self.names), kept

    def siblings(self) -> tuple[np.ndarray, np.ndarray]:
        """Rows by their parents and order, and where the row's group begins there."""
        if self._order is None:
            self._order = np.argsort(self.above, kind="stable")
            up = self.above[self._order]
            head = np.concatenate(([True], up[1:] != up[:-1]))
            self._group = np.maximum.accumulate(np.where(head, np.arange(self.n), 0))
        return self._order, self._group

    def earlier(self, flag: np.ndarray) -> np.ndarray:
        """Whether an earlier sibling has the flag."""
        order, group = self.siblings()
        sums = np.concatenate(([0], np.cumsum(flag[order])))
        out = np.empty(self.n, bool)
        out[order] = sums[:-1] > sums[group]
        return out

    def levels(self) -> list[np.ndarray]:
        """Rows of each depth, from row 0 on; as many array steps as the tree is deep."""
        if self._levels is None:
            order, _ = self.siblings()
            up = self.above[order]
            self._levels = [np.zeros(1, np.int64)]
            while True:
                top = self._levels[-1]
                x, y = np.searchsorted(up, top, "left"), np.searchsorted(up, top, "right")
                sizes = y - x
                total = int(sizes.sum())
                if not total:
                    break
                at = np.repeat(x - np.concatenate(([0], np.cumsum(sizes)[:-1])), sizes) + np.arange(total)
                self._levels.append(np.sort(order[at]))
        return self._levels


class Scans:
    """One for each task; ``fits`` says whether no step goes to a sibling."""

    def __init__(self, automaton: Automaton):
        self.a = automaton
        self.asks: dict[int, list[tuple]] = {}
        self.goes: dict[int, list[int]] = {}
        for q, s in enumerate(automaton.states):
            if s.universal:
                parts = [f for f in _parts(s.match) if f not in (("down", 1, q), ("down", 2, q)) and f[0] != "true"]
                onward = [f for f in parts if f[0] == "down" and automaton.states[f[2]].universal]
                self.goes[q] = [f[2] for f in onward]
                self.asks[q] = [f for f in parts if f not in onward and f[0] != "mark"]

    @staticmethod
    def fits(automaton: Automaton) -> bool:
        return not automaton.preds and all(s.axis in ("child", "descendant", "attribute") for s in automaton.states)

    def begin(self, forest: Forest) -> None:
        self.f = forest
        self._matched: dict[int, np.ndarray] = {}
        self._below: dict[int, np.ndarray] = {}

    # --- filters, upward

    def matched(self, q: int) -> np.ndarray:
        """Rows at which a filter state's own match holds."""
        got = self._matched.get(q)
        if got is None:
            hits = self.f.hits(self.a.states[q].guard)
            got = self._matched[q] = hits[self.value(self.a.states[q].match, hits)]
        return got

    def held_below(self, q: int) -> np.ndarray:
        """Per row, whether a filter state holds in the trees below it."""
        got = self._below.get(q)
        if got is None:
            rows, f = self.matched(q), self.f
            if self.a.states[q].axis == "descendant":
                sums = np.concatenate(([0], np.cumsum(f.mask(rows))))
                got = sums[f.after] > sums[1:]
            else:
                got = f.mask(f.above[rows])
            self._below[q] = got
        return got

    def value(self, f: tuple, rows: np.ndarray) -> np.ndarray:
        op = f[0]
        if op == "down":
            return self.held_below(f[2])[rows]
        if op == "and":
            return self.value(f[1], rows) & self.value(f[2], rows)
        if op == "or":
            return self.value(f[1], rows) | self.value(f[2], rows)
        if op == "not":
            return ~self.value(f[1], rows)
        return np.full(len(rows), op == "true", bool)

    def filters_held(self) -> list[int]:
        return [q for q, s in enumerate(self.a.states) if not s.universal and self.held_below(q)[0]]

    # --- main states, downward

    def run(self, states: frozenset[int], counters: Counters | None = None) -> np.ndarray:
        """Rows that a run marks if ``states`` are asked below row 0; with ``counters`` it counts what a run from match to match would visit."""
        f = self.f
        asked: dict[int, list[np.ndarray]] = {q: [np.zeros(1, np.int64)] for q in states if self.a.states[q].universal}
        demands: dict[int, list[np.ndarray]] = {}
        found: list[np.ndarray] = []
        for q in self._downward():
            if q not in asked:
                continue
            at = np.unique(np.concatenate(asked[q]))
            s = self.a.states[q]
            if s.axis == "descendant":
                outer = at[~f.cover(at)[at]]
                hits = self._inside(f.hits(s.guard), outer)
            else:
                hits = f.hits(s.guard)
                hits = hits[f.mask(at)[f.above[hits]]]
            if s.collects:
                found.append(hits)
                if counters is not None:
                    counters.visited += len(outer)
                continue
            ok = np.ones(len(hits), bool)
            for part in self.asks[q]:
                ok &= self.value(part, hits)
            if s.axis == "descendant" and self.goes[q] and all(self.a.states[r].axis == "descendant" for r in self.goes[q]):
                seen = ~f.cover(hits[ok])[hits]  # inside a match that goes on below, an inner one adds nothing
                hits, ok = hits[seen], ok[seen]
            held = hits[ok]
            if counters is not None:
                counters.visited += len(hits)
                left = hits
                for part in self.asks[q]:
                    left = self._demand(part, left, demands)
                counters.marked += 0 if self.goes[q] else len(held)
            if not self.goes[q]:
                found.append(held)
            for r in self.goes[q]:
                asked.setdefault(r, []).append(held)
        if counters is not None:
            self._count_demands(demands, counters)
        if not found:
            return np.zeros(0, np.int64)
        return found[0] if len(found) == 1 else np.unique(np.concatenate(found))

    def _downward(self) -> list[int]:
        """Main states, each after those that hand over to it."""
        out: list[int] = []

        def put(q: int) -> None:
            if q not in out:
                for r in self.goes[q]:
                    put(r)
                out.append(q)

        for q in self.goes:
            put(q)
        return out[::-1]

    def _inside(self, hits: np.ndarray, outer: np.ndarray) -> np.ndarray:
        if len(outer) == 1:
            return hits[np.searchsorted(hits, outer[0], "right") : np.searchsorted(hits, self.f.after[outer[0]], "left")]
        k = np.searchsorted(outer, hits, "left") - 1  # intervals of ``outer`` are disjoint
        return hits[(k >= 0) & (hits < self.f.after[outer[np.maximum(k, 0)]])] if len(outer) else hits[:0]

    # --- what a run from match to match asks of filters

    def _demand(self, f: tuple, rows: np.ndarray, demands: dict[int, list[np.ndarray]]) -> np.ndarray:
        """Notes which filter states a formula asks below ``rows``, left before right and no further than needed; rows where it holds."""
        op = f[0]
        if op == "down":
            demands.setdefault(f[2], []).append(rows)
            return rows[self.held_below(f[2])[rows]]
        if op == "and":
            return self._demand(f[2], self._demand(f[1], rows, demands), demands)
        if op == "or":
            first = self._demand(f[1], rows, demands)
            rest = self._demand(f[2], np.setdiff1d(rows, first, assume_unique=True), demands)
            return np.union1d(first, rest)
        if op == "not":
            return np.setdiff1d(rows, self._demand(f[1], rows, demands), assume_unique=True)
        return rows if op == "true" else rows[:0]

    def _count_demands(self, demands: dict[int, list[np.ndarray]], counters: Counters) -> None:
        """Filter states in order of their numbers: a state asks only states that were made after it."""
        f, todo = self.f, list(range(len(self.a.states)))
        done: set[int] = set()
        while ready := [q for q in todo if q in demands and q not in done and not any(q in self._inner(p) for p in demands if p not in done)]:
            for q in ready:
                done.add(q)
                s = self.a.states[q]
                at = np.unique(np.concatenate(demands[q]))
                hits = f.hits(s.guard)
                if s.axis == "descendant":
                    x, y = np.searchsorted(hits, at, "right"), np.searchsorted(hits, f.after[at], "left")
                    if s.match[0] == "true":
                        counters.visited += int((x < y).sum())
                        continue
                    true = np.nonzero(f.mask(self.matched(q))[hits])[0]
                    w = np.concatenate((true, [len(hits)]))[np.searchsorted(true, x, "left")]
                    steps = np.zeros(len(hits) + 1, np.int64)
                    np.add.at(steps, x, 1)
                    np.subtract.at(steps, np.maximum(x, np.minimum(w + 1, y)), 1)
                    tried = hits[np.cumsum(steps[:-1]) > 0]
                else:
                    tried = hits[f.mask(at)[f.above[hits]] & ~f.earlier(f.mask(self.matched(q)))[hits]]
                counters.visited += len(tried)
                self._demand(s.match, tried, demands)

    def _inner(self, q: int) -> set[int]:
        """Filter states that a filter state's match asks, at any depth."""
        out: set[int] = set()
        stack = [self.a.states[q].match]
        while stack:
            f = stack.pop()
            if f[0] == "down" and f[2] not in out:
                out.add(f[2])
                stack.append(self.a.states[f[2]].match)
            elif f[0] in ("and", "or", "not"):
                stack += f[1:]
        return out

    # --- what a run over all nodes visits

    def full_counters(self, states: frozenset[int], early: bool, lazy: bool, counters: Counters) -> None:
        """Counts the nodes at which any state is asked, level by level, and the matches that have marked nodes."""
        f, a = self.f, self.a
        qs = list(range(len(a.states)))
        enter = [s.guard.kinds == frozenset(("attrs",)) for s in a.states]
        attrs = f.mask(f.hits(LabelSet(frozenset(("attrs",)), frozenset(("@",)))))
        fits = [f.mask(f.hits(s.guard)) for s in a.states]
        first = f.above == np.arange(f.n) - 1
        blocked: dict[int, np.ndarray] = {}
        for q in qs:
            s = a.states[q]
            if early and not s.universal and not enter[q]:
                true = f.mask(self.matched(q))
                if s.axis == "descendant":
                    true |= self.held_below(q) & ~attrs
                blocked[q] = f.earlier(true)
        asks = [_asked_below(s.match) for s in a.states]
        want = [np.zeros(f.n, bool) for _ in qs]
        left = [np.zeros(f.n, bool) for _ in qs]
        short = np.zeros(f.n, bool)  # rows below which a collected range answers
        for q in states:
            left[q][0] = True
        levels = f.levels()
        for d, rows in enumerate(levels):
            if d:
                up, any_asked = f.above[rows], np.zeros(len(rows), bool)
                go = ~short[up]
                for q in qs:
                    w = left[q][up] & go
                    if enter[q]:
                        w &= first[rows]
                    elif q in blocked:
                        w &= ~blocked[q][rows]
                    want[q][rows] = w
                    any_asked |= w
                counters.visited += int(any_asked.sum())
                for q in qs:
                    s, w = a.states[q], want[q][rows]
                    if s.axis == "descendant":
                        left[q][rows] |= w & ~attrs[rows]
                    if asks[q]:
                        m = w & fits[q][rows]
                        for r in asks[q]:
                            left[r][rows] |= m
            if d and lazy:
                number = sum(left[q][rows].astype(np.int8) for q in qs)
                for q in qs:
                    if a.states[q].collects:
                        short[rows] |= left[q][rows] & (number == 1)
        some = [np.zeros(f.n, bool) for _ in qs]  # marked nodes in the trees below
        for q in qs:
            if a.states[q].collects:
                some[q] |= short & left[q]
        for rows in reversed(levels[1:]):
            for q in qs:
                s = a.states[q]
                if not s.universal:
                    continue
                ok = want[q][rows] & fits[q][rows]
                for part in self.asks[q]:
                    ok &= self.value(part, rows)
                inner = ("down", 1, q) in _parts(s.match)
                mine = np.zeros(len(rows), bool)
                for r in self.goes[q]:
                    mine |= some[r][rows]
                if ("mark",) in _parts(s.match):
                    mine[:] = True
                if inner:
                    mine |= some[q][rows]
                loop = some[q][rows] & ~attrs[rows] if s.axis == "descendant" else np.zeros(len(rows), bool)
                own = np.where(ok, mine, want[q][rows] & loop)
                up = f.above[rows]
                if not enter[q]:  # siblings stand together in a level
                    sums = np.cumsum(own)
                    mine |= sums[np.searchsorted(up, up, "right") - 1] > sums
                counters.marked += int((ok & mine).sum())
                some[q][up[own]] = True


def _parts(f: tuple) -> list[tuple]:
    return _parts(f[1]) + _parts(f[2]) if f[0] == "and" else [f]


def _asked_below(f: tuple) -> set[int]:
    if f[0] == "down":
        return {f[2]} if f[1] == 1 else set()
    return set().union(*(_asked_below(x) for x in f[1:])) if f[0] in ("and", "or", "not") else set()
