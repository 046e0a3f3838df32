"""Parsed paths: a list of steps, each with an axis, a node test and filters."""

from __future__ import annotations

from dataclasses import dataclass, field

AXES = ("child", "descendant", "descendant-or-self", "self", "attribute", "following-sibling", "following", "parent", "ancestor", "preceding", "preceding-sibling")


@dataclass(frozen=True)
class Step:
    axis: str
    test: str  # a name, "*", "text()" or "node()"
    filters: tuple[Filter, ...] = ()


@dataclass(frozen=True)
class Path:
    absolute: bool
    steps: tuple[Step, ...]


@dataclass(frozen=True)
class And:
    left: Filter
    right: Filter


@dataclass(frozen=True)
class Or:
    left: Filter
    right: Filter


@dataclass(frozen=True)
class Not:
    inner: Filter


@dataclass(frozen=True)
class Exists:
    path: Path


@dataclass(frozen=True)
class ValuePred:
    """``kind`` is contains, starts-with, ends-with, =, !=, <, <=, >, >= or a registered name."""

    kind: str
    path: Path
    word: str = field(default="")


Filter = And | Or | Not | Exists | ValuePred


def value_preds(f: Filter) -> list[ValuePred]:
    if isinstance(f, ValuePred):
        return [f]
    if isinstance(f, (And, Or)):
        return value_preds(f.left) + value_preds(f.right)
    if isinstance(f, Not):
        return value_preds(f.inner)
    return [v for s in f.path.steps for g in s.filters for v in value_preds(g)]


def labels_of(path: Path) -> set[str]:
    """Every name that the path or its filters test; "*" if some test admits any label."""
    out: set[str] = set()

    def of_filter(f: Filter) -> None:
        if isinstance(f, (And, Or)):
            of_filter(f.left), of_filter(f.right)
        elif isinstance(f, Not):
            of_filter(f.inner)
        else:
            of_path(f.path)

    def of_path(p: Path) -> None:
        for s in p.steps:
            if s.axis != "self" or s.test != "node()":
                out.add("*" if s.test in ("*", "node()", "text()") else s.test)
            for f in s.filters:
                of_filter(f)

    of_path(path)
    return out
