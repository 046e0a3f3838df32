"""Which labels stand in which relation to which, for pruning paths before they run."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treeloom.xpath.ast import Path, Step


#: Labels whose reach one pass of windows follows.
LABELS_A_PASS = 64


def _ancestors(nodes: DataFrame, labels: list[str]) -> DataFrame:
    """``nodes`` with ``above``: those of ``labels`` that elements over a node in its own fragment have."""
    w = Window.partitionBy("doc", "frag").orderBy("pre").rowsBetween(Window.unboundedPreceding, -1)
    reach = [F.when(F.max(F.when((F.col("kind") == "elem") & (F.col("label") == x), F.col("last"))).over(w) >= F.col("pre"), F.lit(x)) for x in labels]
    return nodes.withColumn("above", F.array_compact(F.array(*reach)))


def _descendants(nodes: DataFrame) -> DataFrame:
    """a, b of every element b below an element a: one window in document order inside fragments, whatever the depth, and the labels
    of each fragment with those of the spine above it."""
    rows = nodes.select("doc", "frag", "pre", "last", "parent", "label", "kind")
    labels = sorted(r[0] for r in rows.filter("kind = 'elem'").select("label").distinct().collect())
    spined = not rows.filter("frag = -1").isEmpty()
    if spined:
        up = rows.filter("frag <> -1").groupBy("doc", "frag").agg(F.min_by("parent", "pre").alias("up"))
        under = rows.filter("frag <> -1 and kind = 'elem'").select("doc", "frag", "label").distinct().join(up, ["doc", "frag"]).select("doc", "up", F.col("label").alias("b")).distinct()
    frames = [rows.select(F.col("label").alias("a"), F.col("label").alias("b")).filter("false")]
    for k in range(0, len(labels), LABELS_A_PASS):
        some = labels[k : k + LABELS_A_PASS]
        frames.append(_ancestors(rows.filter("kind = 'elem'"), some).select(F.explode("above").alias("a"), F.col("label").alias("b")).distinct())
        if spined:
            own = F.when((F.col("kind") == "elem") & F.col("label").isin(some), F.array("label")).otherwise(F.array().cast("array<string>"))
            spine = _ancestors(rows.filter("frag = -1"), some).select("doc", F.col("pre").alias("up"), F.explode(F.array_union("above", own)).alias("a"))
            frames.append(under.join(spine, ["doc", "up"]).select("a", "b").distinct())
    return reduce(DataFrame.unionAll, frames).distinct()


def build_pairs(nodes: DataFrame) -> DataFrame:
    """axis (child, descendant, following-sibling, following), a, b: the pairs of element labels that occur."""
    e = nodes.filter("kind = 'elem'").select("doc", "pre", "last", "parent", "label")
    up = e.select("doc", F.col("pre").alias("parent"), F.col("label").alias("a"))
    child = e.join(up, ["doc", "parent"]).select(F.lit("child").alias("axis"), "a", F.col("label").alias("b")).distinct()
    desc = _descendants(nodes).select(F.lit("descendant").alias("axis"), "a", "b")
    per = e.groupBy("doc", "parent", "label").agg(F.min("pre").alias("lo"), F.max("pre").alias("hi"))
    sib = per.alias("x").join(per.alias("y"), ["doc", "parent"]).filter("x.lo < y.hi").select(F.lit("following-sibling").alias("axis"), F.col("x.label").alias("a"), F.col("y.label").alias("b")).distinct()
    span = e.groupBy("doc", "label").agg(F.min("last").alias("lo"), F.max("pre").alias("hi"))
    foll = span.alias("x").join(span.alias("y"), "doc").filter("x.lo < y.hi").select(F.lit("following").alias("axis"), F.col("x.label").alias("a"), F.col("y.label").alias("b")).distinct()
    return child.unionAll(desc).unionAll(sib).unionAll(foll)


def named(step: Step) -> str | None:
    """The element label that a step asks for, if it asks for one."""
    return step.test if step.axis in ("child", "descendant", "following-sibling", "following") and step.test not in ("*", "text()", "node()") else None


def hopeless(steps: tuple[Step, ...], above: str | None, pairs: set[tuple[str, str, str]]) -> bool:
    """Whether a relative path from a node labelled ``above`` asks for a pair of labels that the tree does not have."""
    for s in steps:
        name = named(s)
        if name is not None and above is not None and (s.axis, above, name) not in pairs:
            return True
        above = above if s.axis == "self" else name
    return False


def provably_empty(path: Path, pairs: set[tuple[str, str, str]], labels: set[str]) -> bool:
    """Whether the main path asks for a label or a pair of labels that the tree does not have."""
    before: str | None = None
    for s in path.steps:
        name = named(s)
        if name is not None and name not in labels:
            return True
        if name is not None and before is not None and (s.axis, before, name) not in pairs:
            return True
        before = name if s.axis != "self" else before
    return False
