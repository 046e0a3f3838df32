"""Navigation over interval-coded nodes as column expressions, windows and joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, WindowSpec
from pyspark.sql import functions as F


def _in_doc() -> WindowSpec:
    return Window.partitionBy("doc")


def open_position() -> Column:
    """Position of the opening parenthesis."""
    return 2 * F.col("pre") - F.col("depth")


def close_position() -> Column:
    return open_position() + 2 * subtree_size() - 1


def subtree_size() -> Column:
    return F.col("last") - F.col("pre") + 1


def is_ancestor(x: str, y: str) -> Column:
    """Whether the node of alias ``x`` is an ancestor of (or is) the one of alias ``y``."""
    return (F.col(f"{x}.doc") == F.col(f"{y}.doc")) & F.col(f"{y}.pre").between(F.col(f"{x}.pre"), F.col(f"{x}.last"))


def siblings(nodes: DataFrame) -> DataFrame:
    """Adds first_child and next_sibling (pre of the node, null if none)."""
    w = Window.partitionBy("doc", "parent").orderBy("pre")
    return nodes.withColumn("first_child", F.when(F.col("last") > F.col("pre"), F.col("pre") + 1)).withColumn("next_sibling", F.lead("pre").over(w))


def child(nodes: DataFrame, i: int) -> DataFrame:
    """The i-th child of every node that has one."""
    return nodes.filter(F.col("ord") == i)


def subtree_tags(nodes: DataFrame, label: str) -> DataFrame:
    """Adds n_label: nodes of ``label`` in the subtree, the node included; two ranks as running counts."""
    hit = F.when((F.col("label") == label) & (F.col("kind") == "elem"), 1).otherwise(0)
    upto = nodes.withColumn("__upto", F.sum(hit).over(_in_doc().orderBy("pre"))).withColumn("__own", hit)
    # the count at the end of the subtree: last is the pre of some node
    at_end = upto.select("doc", F.col("pre").alias("last"), F.col("__upto").alias("__end"))
    return upto.join(at_end, ["doc", "last"]).withColumn("n_label", F.col("__end") - F.col("__upto") + F.col("__own")).drop("__upto", "__own", "__end")


def _label_pre(label: str) -> Column:
    return F.when((F.col("label") == label) & (F.col("kind") == "elem"), F.col("pre"))


def tagged_desc(nodes: DataFrame, label: str) -> DataFrame:
    """Adds tagged_desc: the first node of ``label`` strictly below.

    The frame runs in reversed order, so that it stays open at its start: linear after one sort.
    """
    w = _in_doc().orderBy(F.desc("pre")).rowsBetween(Window.unboundedPreceding, -1)
    next_ = F.min(_label_pre(label)).over(w)
    return nodes.withColumn("tagged_desc", next_).withColumn("tagged_desc", F.when(F.col("tagged_desc") <= F.col("last"), F.col("tagged_desc")))


def tagged_foll(nodes: DataFrame, label: str) -> DataFrame:
    """Adds tagged_foll: the first node of ``label`` after the subtree, found as of ``last`` on a union of both."""
    marks = nodes.select("doc", F.col("pre").alias("at"), _label_pre(label).alias("hit"), F.lit(None).cast("long").alias("pre")).filter("hit is not null")
    asks = nodes.select("doc", F.col("last").alias("at"), F.lit(None).cast("long").alias("hit"), "pre")
    # a mark at the asked position is inside the subtree: in reversed order it must come after the question
    w = _in_doc().orderBy(F.desc("at"), F.col("hit").isNotNull()).rowsBetween(Window.unboundedPreceding, -1)
    found = marks.unionByName(asks).withColumn("tagged_foll", F.min("hit").over(w)).filter("hit is null").select("doc", "pre", "tagged_foll")
    return nodes.join(found, ["doc", "pre"])


def tagged_prec(nodes: DataFrame, label: str) -> DataFrame:
    """Adds tagged_prec: the last node of ``label`` that ended before this one began (so no ancestor)."""
    marks = nodes.filter(_label_pre(label).isNotNull()).select("doc", F.col("last").alias("at"), F.col("pre").alias("hit"), F.lit(None).cast("long").alias("pre"))
    asks = nodes.select("doc", F.col("pre").alias("at"), F.lit(None).cast("long").alias("hit"), "pre")
    w = _in_doc().orderBy("at", F.col("hit").isNotNull()).rowsBetween(Window.unboundedPreceding, -1)
    found = marks.unionByName(asks).withColumn("tagged_prec", F.max("hit").over(w)).filter("hit is null").select("doc", "pre", "tagged_prec")
    return nodes.join(found, ["doc", "pre"])


def text_ranges(nodes: DataFrame) -> DataFrame:
    """Adds first_text and last_text: numbers (from 1, in the document) of the text leaves in the subtree, null if none."""
    hit = F.when(F.col("kind") == "text", 1).otherwise(0)
    upto = nodes.withColumn("__upto", F.sum(hit).over(_in_doc().orderBy("pre"))).withColumn("__own", hit)
    at_end = upto.select("doc", F.col("pre").alias("last"), F.col("__upto").alias("__end"))
    out = upto.join(at_end, ["doc", "last"]).withColumn("__first", F.col("__upto") - F.col("__own") + 1)
    some = F.col("__end") >= F.col("__first")
    return out.withColumn("first_text", F.when(some, F.col("__first"))).withColumn("last_text", F.when(some, F.col("__end"))).drop("__upto", "__own", "__end", "__first")


def topmost(nodes: DataFrame, label: str) -> DataFrame:
    """Nodes of ``label`` below no other of it (within a fragment): partition and prune."""
    hit = nodes.filter((F.col("label") == label) & (F.col("kind") == "elem"))
    w = Window.partitionBy("doc", "frag").orderBy("pre").rowsBetween(Window.unboundedPreceding, -1)
    return hit.withColumn("__reach", F.max("last").over(w)).filter("__reach is null or __reach < pre").drop("__reach")


def bottom_most(nodes: DataFrame, label: str) -> DataFrame:
    """Nodes of ``label`` above no other of it."""
    hit = nodes.filter((F.col("label") == label) & (F.col("kind") == "elem"))
    w = Window.partitionBy("doc", "frag").orderBy(F.desc("pre")).rowsBetween(Window.unboundedPreceding, -1)
    return hit.withColumn("__next", F.min("pre").over(w)).filter("__next is null or __next > last").drop("__next")


def recursive_counts(nodes: DataFrame) -> DataFrame:
    """label, n, n_recursive: nodes that lie below a node of their own label."""
    w = Window.partitionBy("doc", "frag", "label").orderBy("pre").rowsBetween(Window.unboundedPreceding, -1)
    rows = nodes.filter("kind = 'elem'").withColumn("__reach", F.max("last").over(w))
    return rows.groupBy("label").agg(F.count("*").alias("n"), F.count_if(F.col("__reach") >= F.col("pre")).alias("n_recursive"))


def node_of_text(nodes: DataFrame, ids: DataFrame) -> DataFrame:
    """The leaves of text numbers ``ids(doc, text_no)``."""
    numbered = nodes.filter("kind = 'text'").withColumn("text_no", F.row_number().over(_in_doc().orderBy("pre")).cast("long"))
    return numbered.join(ids, ["doc", "text_no"], "left_semi")
