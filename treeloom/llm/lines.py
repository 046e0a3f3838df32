"""Line deduplication by a fixed-depth tree of line templates.

A line descends the tree by its token count and then by its leading third of tokens, ``LEAD`` at most; tokens that hold a digit
count as the variable field ``<*>``.  The rest of its tokens fall into up to ``SEGMENTS`` segments of about equal length.  The leaf holds
templates: the line itself, and the line with any one segment generalised to variable fields, from ``WIDE`` tokens on with any two
(lines under four tokens have only themselves).  Lines that share a template agree in their count, their leading tokens and all other
segments; two fields that vary may lie anywhere behind the leading tokens.

A template that at least ``min_docs`` documents hold is recurring.  Its lines stay in the document with the
smallest id (then row key) and are dropped everywhere else.  All counts are aggregations of hashes with map-side
sums, and joins with them treat frequent templates apart: no leaf is ever gathered in one task, and texts move once, to lose
their lines.  A template is known by the hash of its leaf and one of its own, 128 bits together.

Lines end at ``\\n``; lines without a token are kept.  Null texts stay null.  Rows are told apart by 128 bits of id and text:
repeated rows are one document here, and each gets the same lines dropped.  An empty table gives no rows.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import combinations

import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treeloom.llm.store import discard, fresh, keyed_join, lean, row_identity, saved

LEAD = 3
SEGMENTS = 6
WIDE = 12
MIN_DOCS = 5
_DIGIT = re.compile(rb"[0-9]").search


def lead_of(n: int) -> int:
    """Leading tokens of a line of n tokens that are levels of the tree."""
    return min(LEAD, max(1, n // 3))


def line_segments(line: bytes) -> tuple[int, int, list[int]] | None:
    """(tokens, leaf, segments), the latter two as hashes; None without a token."""
    t = line.split()  # at blank and \x09-\x0D
    if not t:
        return None
    if _DIGIT(line):
        t = [b"<*>" if _DIGIT(x) else x for x in t]
    n, digest = len(t), xxhash.xxh3_64_intdigest
    lead = lead_of(n)
    rest = n - lead
    parts = min(SEGMENTS, rest)
    # the segment of rest token q is q * parts // rest
    cuts = [lead + -(-i * rest // parts) for i in range(parts + 1)] if parts else []
    return n, digest(b" ".join(t[:lead]), n) - 2**63, [digest(b" ".join(t[x:y])) - 2**63 for x, y in zip(cuts, cuts[1:])]


def template_lines(docs: DataFrame) -> DataFrame:
    """r1, r2, doc_id, line number, tokens, leaf and segments of every line with a token of ``docs(r1, r2, doc_id, text)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            owner, number, sizes, leaves, hashes = [], [], [], [], []
            for i, text in enumerate(batch.column("text")):
                if not text.is_valid:
                    continue
                for k, line in enumerate(text.as_py().encode("utf-8", "surrogatepass").split(b"\n")):
                    if (got := line_segments(line)) is not None:
                        owner.append(i)
                        number.append(k)
                        sizes.append(got[0])
                        leaves.append(got[1])
                        hashes.append(got[2])
            at = pa.array(owner, pa.int64())
            yield pa.RecordBatch.from_arrays(
                [*(batch.column(c).take(at) for c in ("r1", "r2", "doc_id")), pa.array(number, pa.int32()), pa.array(sizes, pa.int32()), pa.array(leaves, pa.int64()), pa.array(hashes, pa.list_(pa.int64()))],
                ["r1", "r2", "doc_id", "line", "tokens", "leaf", "segments"],
            )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("r1", "r2", "doc_id", "text").mapInArrow(lean(run), f"r1 long, r2 long, doc_id {kind}, line int, tokens int, leaf long, segments array<long>")


def _without(number: int, out: tuple[int, ...]) -> Column:
    """Hash of a template whose segments ``out`` are variable."""
    return F.xxhash64(F.lit(number), *[F.get("segments", F.lit(i)) for i in range(SEGMENTS) if i not in out])


def templates() -> Column:
    """Hashes of all templates of a line; numbers keep those with other variable segments apart."""
    whole = _without(0, ())
    one = [F.when(F.size("segments") > i, _without(1 + i, (i,))) for i in range(SEGMENTS)]
    two = [_without(1 + SEGMENTS + k, pair) for k, pair in enumerate(combinations(range(SEGMENTS), 2))]
    some = F.when(F.col("tokens") >= WIDE, F.array(whole, *two)).when(F.col("tokens") >= 4, F.filter(F.array(whole, *one), lambda t: t.isNotNull()))
    return some.otherwise(F.array(whole))


def dropped_lines(docs: DataFrame, min_docs: int) -> DataFrame:
    """r1, r2, drop (numbers of the lines to drop) of each row of ``docs(r1, r2, doc_id, text)`` that loses any."""
    lines = saved(template_lines(docs), "lines")
    leaves = saved(lines.groupBy("leaf").agg(F.count("*").alias("n")).filter(F.col("n") >= min_docs), "leaves", few_files=True)
    rows = keyed_join(lines, leaves, ["leaf"], "n", lines.count(), "left_semi").select("r1", "r2", "doc_id", "line", "leaf", F.explode(templates()).alias("t"))
    rows = saved(rows, "templates", few_files=True)
    discard(lines, leaves)
    key = ["leaf", "t"]
    often = saved(rows.groupBy(*key).agg(F.count("*").alias("n")).filter(F.col("n") >= min_docs), "often", few_files=True)
    held = saved(keyed_join(rows, often, key, "n", rows.count(), "left_semi"), "held", few_files=True)
    discard(rows, often)
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "r1", "r2"))
    docs_of = held.groupBy(*key, "r1", "r2").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("lines"))
    recurring = docs_of.groupBy(*key).agg(F.count("*").alias("docs"), F.sum("lines").alias("n"), first.alias("first")).filter(F.col("docs") >= min_docs)
    recurring = saved(recurring.select(*key, "n", F.col("first.r1").alias("k1"), F.col("first.r2").alias("k2")), "recurring", few_files=True)
    gone = keyed_join(held, recurring, key, "n", held.count()).filter("r1 <> k1 or r2 <> k2").select("r1", "r2", "line").distinct()
    return gone.groupBy("r1", "r2").agg(F.collect_list("line").alias("drop"))


def drop_recurring_lines(docs: DataFrame, min_docs: int = MIN_DOCS) -> DataFrame:
    """Every row of ``docs`` with the text that is left, ``n_lines`` and ``n_dropped``; other columns as they are."""
    own = [c for c in docs.columns if c.lower() not in ("n_lines", "n_dropped")]
    k1, k2, drop_col = fresh([*own, "n_lines", "n_dropped"], "r1", "r2", "drop")
    r1, r2 = row_identity("doc_id", "text")
    keyed = docs.select(*[F.col(f"`{c}`") for c in own], r1.alias(k1), r2.alias(k2))
    gone = dropped_lines(keyed.select(F.col(k1).alias("r1"), F.col(k2).alias("r2"), "doc_id", "text"), min_docs).select(F.col("r1").alias(k1), F.col("r2").alias(k2), F.col("drop").alias(drop_col))
    place = [c.lower() for c in own].index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, n, lost = [], [], []
            for text, drop in zip(batch.column(place).to_pylist(), batch.column(drop_col).to_pylist()):
                lines = text.split("\n") if text is not None else []
                n.append(len(lines))
                lost.append(len(drop or ()))
                if drop:
                    bad = set(drop)
                    text = "\n".join(x for i, x in enumerate(lines) if i not in bad)
                texts.append(text)
            cols = [batch.column(i) for i in range(len(own))]
            cols[place] = pa.array(texts, cols[place].type)
            yield pa.RecordBatch.from_arrays([*cols, pa.array(n, pa.int64()), pa.array(lost, pa.int64())], [*own, "n_lines", "n_dropped"])

    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in own) + ", n_lines long, n_dropped long"
    return keyed.join(gone, [k1, k2], "left").select(*[F.col(f"`{c}`") for c in own], drop_col).mapInArrow(lean(run), schema)
