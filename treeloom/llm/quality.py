"""Quality rules as a short-circuit cascade.

Every rule rejects a document on measures of its whole text.  On a bounded sample each rule's cost (seconds a
document) and selectivity (share it rejects) are estimated; the cascade asks the rules in falling order of rejection
per cost and stops at the first that rejects.  The order changes the time, never the verdict.

Words are the maximal runs of characters other than blank and \\x09-\\x0D.  Null and empty texts have no words, fail
the base test and are not kept.  Repeated rows get repeated answers.
"""

from __future__ import annotations

import re
import time
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treeloom.llm.store import lean

_SYMBOLS = re.compile(rb"[#*$%&|<>]")
_MARKS = re.compile(rb"[!?]")


class Measured:
    """Measures of one text, each taken when first asked for."""

    def __init__(self, text: str | None):
        self.data = (text or "").encode("utf-8", "surrogatepass")
        self.words = self.data.split()  # bytes split at exactly \x09-\x0D and blank
        self._got: dict[str, int] = {}

    def __getattr__(self, name: str) -> int:
        got = self._got.get(name)
        if got is None:
            self._got[name] = got = getattr(type(self), f"_{name}")(self)
        return got

    def _n_words(self) -> int:
        return len(self.words)

    def _word_chars(self) -> int:
        return len(b"".join(self.words).decode("utf-8", "surrogatepass"))

    def _n_symbols(self) -> int:
        return len(_SYMBOLS.findall(self.data))

    def _n_marks(self) -> int:
        return len(_MARKS.findall(self.data))

    def _lines(self) -> Counter:
        return Counter(x for x in self.data.split(b"\n") if x.split())

    def _n_lines(self) -> int:
        return self.lines.total()

    def _n_dup_lines(self) -> int:
        return self.lines.total() - len(self.lines)

    def _n_repeat_words(self) -> int:
        """Words inside 3-word windows that the text holds twice or more."""
        w = self.words
        windows = list(zip(w, w[1:], w[2:]))
        count = Counter(windows)
        if len(count) == len(windows):
            return 0
        covered = bytearray(len(w))
        for i, x in enumerate(windows):
            if count[x] > 1:
                covered[i : i + 3] = b"\1\1\1"
        return covered.count(1)

    def _n_letterless(self) -> int:
        """Words without an ASCII letter and without any character beyond ASCII."""
        return sum(1 for w in self.words if not _LETTER(w))


_LETTER = re.compile(rb"[A-Za-z\x80-\xff]").search


@dataclass(frozen=True)
class Rule:
    name: str
    rejects: Callable[[Measured], bool]


#: Applied to texts that pass the base test (over 49 words, at most half of them in repeated windows).
RULES = (
    Rule("symbols", lambda m: 10 * m.n_symbols > m.n_words),
    Rule("short_words", lambda m: m.word_chars < 3 * m.n_words),
    Rule("long_words", lambda m: m.word_chars > 12 * m.n_words),
    Rule("marks", lambda m: 10 * m.n_marks > 3 * m.n_words),
    Rule("repeated_lines", lambda m: 10 * m.n_dup_lines > 3 * m.n_lines),
    Rule("letterless_words", lambda m: 10 * m.n_letterless > 3 * m.n_words),
)
BASE = Rule("base", lambda m: m.n_words < 50 or 100 * m.n_repeat_words > 50 * m.n_words)


def profile(texts: list[str | None], rules: tuple[Rule, ...]) -> list[tuple[str, float, float]]:
    """(rule, seconds a document, share rejected) of each rule taken alone."""
    out = []
    for rule in rules:
        docs = [Measured(t) for t in texts]
        began = time.perf_counter()
        rejected = sum(bool(d.words) and rule.rejects(d) for d in docs)
        out.append((rule.name, (time.perf_counter() - began) / max(1, len(docs)), rejected / max(1, len(docs))))
    return out


def ordered(rules: tuple[Rule, ...], found: list[tuple[str, float, float]]) -> tuple[Rule, ...]:
    worth = {name: (share + 1e-4) / (cost + 1e-9) for name, cost, share in found}
    return tuple(sorted(rules, key=lambda r: -worth[r.name]))


def cascade_order(docs: DataFrame, rules: tuple[Rule, ...], sample_rows: int) -> tuple[Rule, ...]:
    """Order from a sample of ``sample_rows`` texts (the sample decides speed alone)."""
    return ordered(rules, profile(sampled(docs, sample_rows), rules))


def sampled(docs: DataFrame, rows: int) -> list[str | None]:
    """Texts of ``rows`` rows out of all, those with the least hashes; tasks hand over that many hashes each, and no text but the chosen."""
    keyed = docs.select("text", F.xxhash64(F.lit(17), "doc_id", "text").alias("h"))
    least = [r[0] for r in keyed.select("h").orderBy("h").limit(rows).collect()]
    if not least:
        return []
    texts = dict(keyed.filter(F.col("h") <= least[-1]).groupBy("h").agg(F.max("text")).collect())  # a row for each of at most `rows` hashes
    return [texts[h] for h in least]


def cascade_report(docs: DataFrame, rules: tuple[Rule, ...] = RULES, sample_rows: int = 64) -> DataFrame:
    """place (from 1), rule, cost_us (microseconds a document), selectivity: the order that the sample leads to, and why."""
    found = profile(sampled(docs, sample_rows), rules)
    by_name = {name: (1e6 * cost, share) for name, cost, share in found}
    rows = [(i, r.name, *by_name[r.name]) for i, r in enumerate(ordered(rules, found), 1)]
    return docs.sparkSession.createDataFrame(rows, "place int, rule string, cost_us double, selectivity double")


def judge_quality(docs: DataFrame, rules: tuple[Rule, ...] = RULES, sample_rows: int = 64) -> DataFrame:
    """doc_id, the base measures, base_failed and kept, for every row of ``docs``."""
    names = [r.name for r in cascade_order(docs, rules, sample_rows)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by_name = {r.name: r for r in rules}
        chain = [by_name[n] for n in names]
        fields = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
        for batch in batches:
            cols: list[list[int]] = [[] for _ in fields]
            failed, why = [], []
            for text in batch.column("text"):
                m = Measured(text.as_py())
                for col, f in zip(cols, fields):
                    col.append(getattr(m, f))
                failed.append(BASE.rejects(m))
                why.append("base" if failed[-1] else next((r.name for r in chain if r.rejects(m)), None))
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), *(pa.array(c, pa.int64()) for c in cols), pa.array(failed, pa.bool_()), pa.array([x is None for x in why], pa.bool_())],
                ["doc_id", *fields, "base_failed", "kept"],
            )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(lean(run), f"doc_id {kind}, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean")


def keep_good(docs: DataFrame, rules: tuple[Rule, ...] = RULES, sample_rows: int = 64) -> DataFrame:
    """The rows of ``docs`` that the base test and the cascade keep, all columns, without a shuffle."""
    names = [r.name for r in cascade_order(docs, rules, sample_rows)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by_name = {r.name: r for r in rules}
        # measures that cost much come last: a text that another rule rejects never has its windows counted
        chain = [Rule("few_words", lambda m: m.n_words < 50), *(by_name[n] for n in names), BASE]
        for batch in batches:
            keep = []
            for text in batch.column("text"):
                m = Measured(text.as_py())
                keep.append(not any(r.rejects(m) for r in chain))
            yield batch.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(lean(run), docs.schema)
