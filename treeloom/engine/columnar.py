"""Set-at-a-time evaluation: every step filters the candidates of its node test by the nodes of the step before.

Candidates are kept or dropped, never joined out, so no step makes duplicates and none needs a ``distinct``.  Tests of
ancestry are windows in document order over one fragment (running maximum of ``last``, or running minimum of ``pre`` in
reversed order); nodes of the spine, which lie above all fragments and are few, are compared as one list of intervals a document,
and Spark broadcasts these or not by their size.
Parent and sibling tests are equi-joins on (doc, parent).
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from treeloom.sources.trees import Tree
from treeloom.text.plain import text_condition
from treeloom.xpath.ast import And, Exists, Filter, Not, Or, Path, Step, ValuePred
from treeloom.xpath.parser import parse

KEY = ["doc", "pre"]


def test_condition(step: Step) -> Column:
    kind, label = F.col("kind"), F.col("label")
    if step.axis == "attribute":
        return (kind == "attr") & (F.lit(True) if step.test in ("*", "node()") else label == step.test)
    if step.test == "*":
        return kind == "elem"
    if step.test == "text()":
        return kind == "text"
    if step.test == "node()":
        return kind.isin("elem", "text")
    return (kind == "elem") & (label == step.test)


def below_any(candidates: DataFrame, context: DataFrame, or_self: bool = False) -> DataFrame:
    """Candidates with an ancestor (or themselves) in ``context``."""
    cols = candidates.columns
    # a candidate that is also context must meet the others only, unless its own interval counts
    tagged = candidates.withColumn("__c", F.lit(True)).unionByName(context.filter("frag <> -1").select("doc", "frag", "pre", "last").withColumn("__c", F.lit(False)), allowMissingColumns=True)
    first = F.col("__c") if or_self else ~F.col("__c")
    w = Window.partitionBy("doc", "frag").orderBy("pre", first).rowsBetween(Window.unboundedPreceding, 0)
    inside = tagged.withColumn("__reach", F.max(F.when(~F.col("__c"), F.col("last"))).over(w)).filter("__c").withColumn("__in", F.coalesce(F.col("__reach") >= F.col("pre"), F.lit(False)))
    above = context.filter("frag = -1").select(F.col("doc").alias("__d"), F.col("pre").alias("__p"), F.col("last").alias("__l"))
    ivs = above.groupBy("__d").agg(F.collect_list(F.struct("__p", "__l")).alias("__ivs"))
    low = (lambda i: i["__p"] <= F.col("pre")) if or_self else (lambda i: i["__p"] < F.col("pre"))
    joined = inside.join(ivs, F.col("doc") == F.col("__d"), "left")
    return joined.filter(F.col("__in") | F.coalesce(F.exists("__ivs", lambda i: low(i) & (i["__l"] >= F.col("pre"))), F.lit(False))).select(*cols)


def above_any(candidates: DataFrame, below: DataFrame, or_self: bool = False) -> DataFrame:
    """Candidates with a descendant (or themselves) in ``below``."""
    cols = candidates.columns
    tagged = candidates.filter("frag <> -1").withColumn("__c", F.lit(True)).unionByName(below.select("doc", "frag", "pre").withColumn("__c", F.lit(False)), allowMissingColumns=True)
    first = F.col("__c") if or_self else ~F.col("__c")
    # reversed order: the frame stays open at its start and the cost linear
    w = Window.partitionBy("doc", "frag").orderBy(F.desc("pre"), first).rowsBetween(Window.unboundedPreceding, 0)
    inside = tagged.withColumn("__next", F.min(F.when(~F.col("__c"), F.col("pre"))).over(w)).filter("__c").filter(F.col("__next") <= F.col("last")).select(*cols)
    spine = candidates.filter("frag = -1")
    s = spine.groupBy("doc").agg(F.collect_list(F.struct(F.col("pre").alias("p"), F.col("last").alias("l"))).alias("__spine"))
    low = (lambda i: i["p"] <= F.col("pre")) if or_self else (lambda i: i["p"] < F.col("pre"))
    # one row a document with a spine: the planner broadcasts it, or not, by its size
    over = below.select("doc", "pre").join(s, "doc").select("doc", F.explode(F.filter("__spine", lambda i: low(i) & (i["l"] >= F.col("pre")))).alias("i"))
    hit = over.select("doc", F.col("i.p").alias("pre")).distinct()
    return inside.unionByName(spine.join(hit, KEY, "left_semi").select(*cols))


def _keys(df: DataFrame) -> DataFrame:
    return df.select(*KEY)


class Columnar:
    """Evaluator of paths over one tree. ``value_mode``: "text" tests single texts, "string" the text of the whole element."""

    def __init__(self, tree: Tree, value_mode: str = "text"):
        self.tree, self.value_mode = tree, value_mode

    def candidates(self, step: Step) -> DataFrame:
        return self.tree.nodes.filter(test_condition(step))

    def select(self, path: Path | str) -> DataFrame:
        """The result nodes of an absolute path."""
        path = parse(path) if isinstance(path, str) else path
        out: DataFrame | None = None
        for step in path.steps:
            out = self.from_root(step) if out is None else self.axis(out, self.candidates(step), step.axis)
            for f in step.filters:
                out = self.keep(out, f)
        return out if out is not None else self.tree.nodes.filter("kind = 'doc'")

    def from_root(self, step: Step) -> DataFrame:
        c = self.candidates(step)
        if step.axis == "child":
            return c.filter("depth = 2")
        if step.axis in ("descendant", "descendant-or-self"):
            return c
        return c.filter(F.lit(False))

    def axis(self, context: DataFrame, c: DataFrame, axis: str) -> DataFrame:
        """The candidates that ``axis`` reaches from some node of ``context``."""
        if axis == "self":
            return c.join(_keys(context), KEY, "left_semi")
        if axis == "child":
            return c.join(context.select("doc", F.col("pre").alias("parent")), ["doc", "parent"], "left_semi")
        if axis == "attribute":
            return c.join(context.select("doc", F.col("pre").alias("host")), ["doc", "host"], "left_semi")
        if axis in ("descendant", "descendant-or-self"):
            return below_any(c, context, axis != "descendant")
        if axis == "parent":
            return c.join(context.select("doc", F.col("parent").alias("pre")).distinct(), KEY, "left_semi")
        if axis == "ancestor":
            return above_any(c, context)
        edges = {
            "following-sibling": (["doc", "parent"], F.min("last"), lambda e: F.col("pre") > e),
            "preceding-sibling": (["doc", "parent"], F.max("pre"), lambda e: F.col("last") < e),
            "following": (["doc"], F.min("last"), lambda e: F.col("pre") > e),
            "preceding": (["doc"], F.max("pre"), lambda e: F.col("last") < e),
        }
        by, edge, beyond = edges[axis]
        per = context.groupBy(*by).agg(edge.alias("__edge"))
        return c.join(per, by).filter(beyond(F.col("__edge"))).select(*c.columns)

    def keep(self, context: DataFrame, f: Filter) -> DataFrame:
        """The nodes of ``context`` for which the filter holds."""
        if isinstance(f, And):
            return self.keep(self.keep(context, f.left), f.right)
        if isinstance(f, Or):
            either = _keys(self.keep(context, f.left)).unionAll(_keys(self.keep(context, f.right)))
            return context.join(either, KEY, "left_semi")
        if isinstance(f, Not):
            return context.join(_keys(self.keep(context, f.inner)), KEY, "left_anti")
        return self.pull(context, f.path, f)

    def hits(self, step: Step, pred: ValuePred) -> DataFrame:
        """Nodes of a value path's last step whose text satisfies the predicate."""
        if step.axis == "attribute" or step.test == "text()":
            kind = "attr" if step.axis == "attribute" else "text"
            ok = self.tree.matching(pred.kind, pred.word).filter(F.col("kind") == kind)
            named = ok if step.test in ("text()", "*", "node()") else ok.filter(F.col("label") == step.test)
            return self.candidates(step).join(_keys(named), KEY, "left_semi")
        return self.candidates(step).join(_keys(self.valued(pred)), KEY, "left_semi")

    def valued(self, pred: ValuePred) -> DataFrame:
        """Elements (doc, pre) whose text satisfies the predicate."""
        if self.value_mode == "text":
            return self.tree.matching(pred.kind, pred.word).filter("kind = 'text'").select("doc", F.col("parent").alias("pre"))
        whole = string_values(self.tree)
        return whole.filter(text_condition(pred.kind, F.col("string"), pred.word)).select(*KEY)

    def pull(self, context: DataFrame, path: Path, f: Exists | ValuePred) -> DataFrame:
        """Nodes of ``context`` from which the relative path leads somewhere (to a text that satisfies)."""
        steps = list(path.steps)
        if isinstance(f, ValuePred) and steps == [Step("self", "node()")]:
            attrs = context.filter("kind in ('attr', 'text')").join(_keys(self.tree.matching(f.kind, f.word)), KEY, "left_semi")
            return context.filter("kind = 'elem'").join(_keys(self.valued(f)), KEY, "left_semi").unionByName(attrs)
        reached: DataFrame | None = None
        for i in range(len(steps) - 1, -1, -1):
            step = steps[i]
            here = self.hits(step, f) if isinstance(f, ValuePred) and i == len(steps) - 1 else self.candidates(step)
            if reached is not None:
                here = self.back(here, reached, steps[i + 1].axis)
            for g in step.filters:
                here = self.keep(here, g)
            reached = here
        return self.back(context, reached, steps[0].axis)

    def back(self, context: DataFrame, reached: DataFrame, axis: str) -> DataFrame:
        """Nodes of ``context`` from which ``axis`` leads to a node of ``reached``."""
        if axis == "self":
            return context.join(_keys(reached), KEY, "left_semi")
        if axis == "child":
            return context.join(reached.select("doc", F.col("parent").alias("pre")), KEY, "left_semi")
        if axis == "attribute":
            return context.join(reached.select("doc", F.col("host").alias("pre")), KEY, "left_semi")
        if axis in ("descendant", "descendant-or-self"):
            return above_any(context, reached, axis != "descendant")
        if axis == "parent":
            return context.join(reached.select("doc", F.col("pre").alias("parent")), ["doc", "parent"], "left_semi")
        if axis == "ancestor":
            return below_any(context, reached)
        mirrored = {"following-sibling": "preceding-sibling", "preceding-sibling": "following-sibling", "following": "preceding", "preceding": "following"}
        return self.axis(reached, context, mirrored[axis])


def string_values(tree: Tree) -> DataFrame:
    """doc, pre, string: the texts below every element, joined in document order.

    Texts are handed to each of their ancestors, so the cost is text size times depth, as the string value is by nature.
    """
    texts = tree.texts.filter("kind = 'text'").select("doc", "parent", F.col("pre").alias("at"), "value")
    elems = tree.nodes.filter("kind = 'elem'").select("doc", "pre", F.col("parent").alias("up"))
    depth = tree.nodes.agg(F.max("depth")).first()[0] or 0
    level = texts.withColumnRenamed("parent", "pre")
    parts = [level]
    for _ in range(depth - 2):
        level = level.join(elems, KEY).select("doc", F.col("up").alias("pre"), "at", "value")
        parts.append(level)
    # hop k hands a text to its k-th ancestor; the document node is no element
    every = reduce(DataFrame.unionAll, parts).join(elems.select(*KEY), KEY, "left_semi")
    ordered = F.sort_array(F.collect_list(F.struct("at", "value")))
    return every.groupBy(*KEY).agg(F.array_join(F.transform(ordered, lambda x: x["value"]), "").alias("string"))


def count_nodes(df: DataFrame) -> DataFrame:
    return df.agg(F.count("*").alias("n"))
