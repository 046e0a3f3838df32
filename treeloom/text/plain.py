"""Text predicates on a column: the scan that needs no index."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

_extra: dict[str, Callable[[Column, str], Column]] = {}


def register_text_predicate(name: str, condition: Callable[[Column, str], Column]) -> None:
    """Makes ``name(path, "argument")`` a predicate of paths; ``condition`` gets the text column and the argument."""
    from treeloom.xpath.parser import register_text_function

    register_text_function(name)
    _extra[name] = condition


def text_condition(kind: str, value: Column, word: str) -> Column:
    """Whether ``value`` satisfies the predicate; strings compare in the order of their bytes."""
    w = F.lit(word)
    if kind in _extra:
        return _extra[kind](value, word)
    simple: dict[str, Callable[[], Column]] = {
        "contains": lambda: value.contains(w), "starts-with": lambda: value.startswith(w), "ends-with": lambda: value.endswith(w),
        "=": lambda: value == w, "!=": lambda: value != w, "<": lambda: value < w, "<=": lambda: value <= w, ">": lambda: value > w, ">=": lambda: value >= w,
    }
    if kind not in simple:
        raise ValueError(f"unknown text predicate {kind}")
    return simple[kind]()


def occurrences(value: Column, word: str) -> Column:
    """Occurrences of ``word`` in a text, overlapping ones too."""
    return F.regexp_count(value, F.lit(f"(?=\\Q{word}\\E)")).cast("long")
