"""Alternating marking tree automata over the first-child / next-sibling view of a document."""

from __future__ import annotations

from dataclasses import dataclass, field

#: Formulas are interned tuples, so that equal ones are one object and compare in constant time.
_interned: dict[tuple, tuple] = {}


def _make(*parts: object) -> tuple:
    return _interned.setdefault(parts, parts)


TRUE, FALSE, MARK = _make("true"), _make("false"), _make("mark")


def down(side: int, state: int) -> tuple:
    """State ``state`` holds in the first child (1) or next sibling (2) tree."""
    return _make("down", side, state)


def pred(number: int) -> tuple:
    return _make("pred", number)


def conj(*fs: tuple) -> tuple:
    out = TRUE
    for f in fs:
        if f is FALSE or out is FALSE:
            return FALSE
        out = f if out is TRUE else out if f is TRUE else _make("and", out, f)
    return out


def disj(*fs: tuple) -> tuple:
    out = FALSE
    for f in fs:
        if f is TRUE or out is TRUE:
            return TRUE
        out = f if out is FALSE else out if f is FALSE else _make("or", out, f)
    return out


def neg(f: tuple) -> tuple:
    if f is TRUE or f is FALSE:
        return FALSE if f is TRUE else TRUE
    return f[1] if f[0] == "not" else _make("not", f)


def atoms(f: tuple, side: int) -> frozenset[int]:
    """States that a formula asks of one side."""
    if f[0] == "down":
        return frozenset((f[2],)) if f[1] == side else frozenset()
    return frozenset().union(*(atoms(x, side) for x in f[1:])) if f[0] in ("and", "or", "not") else frozenset()


def has_pred(f: tuple) -> bool:
    return f[0] == "pred" or f[0] in ("and", "or", "not") and any(map(has_pred, f[1:]))


@dataclass(frozen=True)
class LabelSet:
    """Finite (``names``) or co-finite (all but ``names``) set of labels among nodes of some kinds."""

    kinds: frozenset[str]
    names: frozenset[str] = frozenset()
    rest: bool = False

    def has(self, kind: str, label: str) -> bool:
        return kind in self.kinds and ((label in self.names) != self.rest)

    @property
    def finite(self) -> bool:
        return not self.rest


@dataclass(frozen=True)
class State:
    """One step: what it matches, the formula then, and the formula of the loop."""

    axis: str
    universal: bool
    guard: LabelSet
    match: tuple
    loop: tuple
    loop_at_attributes: tuple
    collects: bool = False  # last step below, no filter: marks every node that it matches


@dataclass
class Automaton:
    states: list[State] = field(default_factory=list)
    top: frozenset[int] = frozenset()
    preds: list = field(default_factory=list)

    @property
    def bottom(self) -> frozenset[int]:
        """States that hold on the empty tree: the universal ones."""
        return frozenset(i for i, s in enumerate(self.states) if s.universal)

    def relevant(self) -> list[LabelSet]:
        """Labels on which some state does more than loop."""
        return [s.guard for s in self.states]

    @property
    def can_jump(self) -> bool:
        """Whether the relevant labels are few and every step goes to a child, a descendant or an attribute."""
        return all(s.guard.finite and s.axis != "following-sibling" for s in self.states)
