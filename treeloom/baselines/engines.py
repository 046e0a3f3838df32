"""The engines that the methods are compared with, each giving the same answers by its own way."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from treeloom.automaton.compile import Unsupported, guard_of, to_automaton
from treeloom.automaton.evaluate import Counters, Document, Runner
from treeloom.automaton.model import LabelSet
from treeloom.engine.columnar import KEY, string_values, test_condition
from treeloom.engine.topdown import MAX_SPINE
from treeloom.sources.trees import Tree
from treeloom.text.plain import text_condition
from treeloom.tree.encode import Node, flatten
from treeloom.xpath.ast import And, Filter, Not, Or, Path, ValuePred
from treeloom.xpath.parser import parse


@dataclass(frozen=True)
class Parts:
    """Nodes of fragments, and those above all fragments, which are at hand (None in a tree of whole documents)."""

    below: DataFrame
    above: list[dict] | None


class StepJoin:
    """A column store with interval coding: one join, one ``distinct`` and one sort a step; string values for texts.

    Nodes above all fragments are few and go through the steps apart from the rest, on the driver.  What a plan broadcasts is then at hand
    and waits for no job: as a part of the step before it stood in line behind the scans of all other sides.
    """

    def __init__(self, tree: Tree, value_mode: str = "text"):
        self.tree, self.value_mode = tree, value_mode
        self._kept: dict[tuple[int, int], dict] | None = None

    @property
    def _spine(self) -> dict[tuple[int, int], dict]:
        if self._kept is None:
            rows = self.tree.nodes.filter("frag = -1").limit(MAX_SPINE + 1).collect() if self.tree.spined else []
            if len(rows) > MAX_SPINE:
                raise Unsupported("the spine is too large for the driver")
            self._kept = {(r["doc"], r["pre"]): r.asDict() for r in rows}
        return self._kept

    def _at_hand(self, rows: list[dict]) -> DataFrame:
        schema = self.tree.nodes.schema
        return self.tree.spark.createDataFrame(pa.Table.from_pylist(rows, to_arrow_schema(schema)), schema)

    def _every(self, parts: Parts) -> DataFrame:
        return parts.below.unionByName(self._at_hand(parts.above)) if parts.above else parts.below

    def _over(self, y: dict, axis: str) -> Iterator[tuple[int, int]]:
        """The nodes of the spine from which an axis leads to one of its nodes."""
        at = {"self": "pre", "attribute": "host"}.get(axis, "parent")
        key = (y["doc"], y[at])
        while key in self._spine:
            yield key
            if axis != "descendant":
                return
            key = (y["doc"], self._spine[key]["parent"])

    def _related(self, axis: str) -> Column:
        x, y = (lambda c: F.col(f"x.{c}")), (lambda c: F.col(f"y.{c}"))
        return {
            "child": y("parent") == x("pre"),
            "descendant": (y("pre") > x("pre")) & (y("pre") <= x("last")),
            "self": y("pre") == x("pre"),
            "attribute": y("host") == x("pre"),
            "following-sibling": (y("parent") == x("parent")) & (y("pre") > x("last")),
        }[axis] & (x("doc") == y("doc"))

    def _step(self, context: Parts, candidates: Parts, axis: str, keep: str) -> Parts:
        near = self._related(axis)
        pairs = lambda xs, ys, on=near: xs.alias("x").join(ys.alias("y"), on).select(f"{keep}.*")
        if axis == "following-sibling" and context.above is not None:  # siblings may lie in different fragments, or above them
            every = pairs(self._every(context), self._every(candidates)).distinct()
            return Parts(every.filter("frag <> -1"), [r.asDict() for r in every.filter("frag = -1").collect()])
        # intervals of fragments never cross
        below = pairs(context.below, candidates.below, near & (F.col("x.frag") == F.col("y.frag")) if axis == "descendant" else near)
        if not context.above:
            return Parts(below.distinct(), context.above)
        across = pairs(F.broadcast(self._at_hand(context.above)), candidates.below)
        if keep == "y":
            tops = {(x["doc"], x["pre"]) for x in context.above}
            return Parts(below.unionByName(across).distinct(), [y for y in candidates.above if not tops.isdisjoint(self._over(y, axis))])
        hit = {k for y in candidates.above for k in self._over(y, axis)} | {tuple(r) for r in across.select(*KEY).distinct().collect()}
        return Parts(below.distinct(), [x for x in context.above if (x["doc"], x["pre"]) in hit])

    def _parts(self, condition: Column, guard: LabelSet) -> Parts:
        found = self.tree.nodes.filter(condition)
        if not self.tree.spined:
            return Parts(found, None)
        return Parts(found.filter("frag <> -1"), [r for r in self._spine.values() if guard.has(r["kind"], r["label"])])

    def candidates(self, step) -> Parts:
        return self._parts(test_condition(step), guard_of(step))

    def select(self, path: Path | str) -> DataFrame:
        path = parse(path) if isinstance(path, str) else path
        out = self._parts(F.col("kind") == "doc", LabelSet(frozenset(("doc",)), rest=True))
        for step in path.steps:
            out = self._step(out, self.candidates(step), step.axis, "y")
            for f in step.filters:
                out = self.keep(out, f)
        return self._every(out).orderBy("doc", "pre")

    def keep(self, context: Parts, f: Filter) -> Parts:
        if isinstance(f, And):
            return self.keep(self.keep(context, f.left), f.right)
        if isinstance(f, Or):
            left, right = self.keep(context, f.left), self.keep(context, f.right)
            return Parts(left.below.unionByName(right.below).distinct(), context.above and [r for r in context.above if r in left.above or r in right.above])
        if isinstance(f, Not):
            inner = self.keep(context, f.inner)
            return Parts(context.below.join(inner.below.select(*KEY), KEY, "left_anti"), context.above and [r for r in context.above if r not in inner.above])
        reached: Parts | None = None
        steps = list(f.path.steps)
        for i in range(len(steps) - 1, -1, -1):
            here = self.candidates(steps[i])
            if i == len(steps) - 1 and isinstance(f, ValuePred):
                valued = self._valued(f)
                above = here.above and [r.asDict() for r in self._at_hand(here.above).join(valued, KEY, "left_semi").select(self.tree.nodes.columns).collect()]
                here = Parts(here.below.join(valued, KEY, "left_semi"), above)
            if reached is not None:
                here = self._step(here, reached, steps[i + 1].axis, "x")
            for g in steps[i].filters:
                here = self.keep(here, g)
            reached = here
        return self._step(context, reached, steps[0].axis, "x")

    def _valued(self, p: ValuePred) -> DataFrame:
        texts = self.tree.texts
        hit = text_condition(p.kind, F.col("value"), p.word)
        own = texts.filter("kind = 'attr'").filter(hit).select(*KEY)
        if self.value_mode == "string":
            return own.unionAll(string_values(self.tree).filter(text_condition(p.kind, F.col("string"), p.word)).select(*KEY))
        return own.unionAll(texts.filter("kind = 'text'").filter(hit).select("doc", F.col("parent").alias("pre")))


# --- word index ------------------------------------------------------------------------------------------------------


def build_words(texts: DataFrame) -> DataFrame:
    """word, text_id, n: the inverted table of ``texts(text_id, value)``."""
    words = texts.select("text_id", F.explode(F.split("value", r"[\x20\x09-\x0D]+")).alias("word")).filter("word <> ''")
    return words.groupBy("word", "text_id").agg(F.count("*").alias("n"))


def word_contains(words: DataFrame, texts: DataFrame, pattern: str) -> DataFrame:
    """text_id of texts that hold the pattern: the vocabulary is scanned for its words, then the texts verify."""
    pieces = [p for p in pattern.split(" ") if p]
    hit = None
    for p in pieces:
        own = words.filter(F.col("word").contains(p)).select("text_id").distinct()
        hit = own if hit is None else hit.join(own, "text_id", "left_semi")
    return texts.join(hit, "text_id", "left_semi").filter(F.col("value").contains(pattern)).select("text_id")


def word_boolean(words: DataFrame, every: list[str], none: list[str] = [], some: list[str] = []) -> DataFrame:  # noqa: B006
    """text_id of texts that hold all words of ``every``, one of ``some`` or more (if given) and none of ``none``: one pass over postings."""
    asked = sorted({*every, *none, *some})
    has = lambda w: F.max((F.col("word") == w).cast("int")) == 1
    tests = [has(w) for w in every] + [~has(w) for w in none] + ([reduce(lambda a, b: a | b, [has(w) for w in some])] if some else [])
    hit = words.filter(F.col("word").isin(asked)).groupBy("text_id").agg(reduce(lambda a, b: a & b, tests).alias("ok"))
    return hit.filter("ok").select("text_id")


def word_regex(words: DataFrame, expression: str) -> DataFrame:
    """text_id of texts with a word that the expression matches: the vocabulary is scanned, not the texts."""
    return words.filter(F.col("word").rlike(expression)).select("text_id").distinct()


def ranked(words: DataFrame, n_texts: int, terms: list[str], k: int) -> DataFrame:
    """text_id, score of the k texts that are most about the terms (term count times rarity); not comparable with the rest."""
    hit = words.filter(F.col("word").isin(terms))
    rare = hit.groupBy("word").agg(F.log(F.lit(float(n_texts)) / F.count("*")).alias("idf"))
    scores = hit.join(F.broadcast(rare), "word").groupBy("text_id").agg(F.round(F.sum(F.col("n") * F.col("idf")), 6).alias("score"))
    return scores.orderBy(F.desc("score"), "text_id").limit(k)


# --- scans, streams and pointer structures ---------------------------------------------------------------------------


def plain_scan(texts: DataFrame, pattern: str) -> DataFrame:
    """Occurrences (without overlaps) and texts by one pass over the buffers."""
    n = F.regexp_count("value", F.lit("\\Q" + pattern + "\\E"))
    return texts.agg(F.coalesce(F.sum(n), F.lit(0)).cast("long").alias("occurrences"), F.count_if(F.col("value").contains(pattern)).alias("texts"))


def document_of(top: Node) -> tuple[Document, list[str | None], list[int]]:
    rows = flatten(top)
    num = [np.array([r[i] for r in rows]) for i in (0, 1, 3)]
    return Document(*num, [r[5] for r in rows], [r[6] for r in rows], []), [r[8] for r in rows], num[2].tolist()


def stream_eval(df: DataFrame, make, columns: list[str], key: str, path: str) -> DataFrame:
    """doc, n: results of the path in each document, parsed anew at every run; nothing is indexed.  Works on streams."""
    automaton = to_automaton(parse(path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        runner = Runner(automaton)
        for batch in batches:
            args = [batch.column(c).to_pylist() for c in columns]
            found = []
            for i in range(batch.num_rows):
                doc, values, parents = document_of(make(*(a[i] for a in args)))
                doc.flags = [_holds(p, doc, values, parents) for p in automaton.preds]
                found.append(runner.count(doc, runner.run(doc, Counters())))
            yield pa.RecordBatch.from_arrays([batch.column(key).cast(pa.int64()), pa.array(found, pa.int64())], ["doc", "n"])

    return df.select(*dict.fromkeys([key, *columns])).mapInArrow(run, "doc long, n long")


_TESTS = {
    "contains": lambda v, w: w in v, "starts-with": str.startswith, "ends-with": str.endswith, "=": lambda v, w: v == w, "!=": lambda v, w: v != w,
    "<": lambda v, w: v.encode() < w.encode(), "<=": lambda v, w: v.encode() <= w.encode(), ">": lambda v, w: v.encode() > w.encode(), ">=": lambda v, w: v.encode() >= w.encode(),
}


def _holds(p: ValuePred, doc: Document, values: list[str | None], parents: list[int]) -> list[bool]:
    """Nodes whose own text satisfies a predicate: the text itself, or an element with such a child."""
    out = [False] * len(values)
    test = _TESTS[p.kind]
    for i, v in enumerate(values):
        if v is not None and doc.kind[i] in ("text", "attr") and test(v, p.word):
            out[i] = True
            if doc.kind[i] == "text":
                out[parents[i] - 1] = True
    return out


def pointer_table(nodes: DataFrame, layout: str = "pre") -> DataFrame:
    """doc, pre, first_child, next_sibling and ``place`` (from 1): the order of rows in memory, which is the pre-, in- or post-order of
    the binary tree of first children and next siblings."""
    from treeloom.tree.nav import siblings

    rows = siblings(nodes)
    out = ["doc", "pre", "depth", "first_child", "next_sibling"]
    if layout == "pre":
        return rows.select(*out, F.col("pre").alias("place"))
    if layout == "in":
        # the order in which nodes end: all earlier ones but the open ancestors, and the own subtree
        return rows.select(*out, (F.col("last") - F.col("depth") + 1).alias("place"))
    # after its siblings' subtrees and its own, but before the earlier siblings of itself and of its ancestors, which are still open:
    # their number is a running sum over beginnings and ends
    early = F.col("ord") - 1
    marks = nodes.select("doc", F.col("pre").alias("at"), F.lit(0).alias("end"), early.alias("x"), "pre").unionAll(nodes.select("doc", F.col("last").alias("at"), F.lit(1).alias("end"), -early, F.lit(None).cast("long")))
    w = Window.partitionBy("doc").orderBy("at", "end").rowsBetween(Window.unboundedPreceding, 0)
    open_ = marks.withColumn("open", F.sum("x").over(w)).filter("end = 0").select("doc", "pre", "open")
    up = nodes.select("doc", F.col("pre").alias("parent"), F.col("last").alias("up_last"))
    place = F.coalesce("up_last", "last") - F.col("depth") - F.col("open") + 1
    return rows.join(up, ["doc", "parent"], "left").join(open_, ["doc", "pre"]).select(*out, place.alias("place"))


def pointer_walk(nodes: DataFrame, layout: str) -> DataFrame:
    """doc, n: nodes reached over pointers between the rows of each document as the layout orders them in memory."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None

        def walk(t: pa.Table) -> tuple[int, int]:
            pre, place = t.column("pre").to_numpy(), t.column("place").to_numpy()
            at = np.zeros(len(pre) + 2, np.int64)
            at[pre] = place - 1  # where each node lies; rows come in the order of their place
            first, nxt = (np.where((v := t.column(c).to_numpy(zero_copy_only=False).astype(float)) > 0, at[np.nan_to_num(v).astype(np.int64)], -1).tolist() for c in ("first_child", "next_sibling"))
            n, stack = 0, [int(at[1])]
            while stack:
                i = stack.pop()
                while i >= 0:
                    n += 1
                    if nxt[i] >= 0:
                        stack.append(nxt[i])
                    i = first[i]
            return t.column("doc")[0].as_py(), n

        for batch in batches:
            if batch.num_rows:
                t = pa.Table.from_batches([batch])
                t = t if held is None else pa.concat_tables([held, t])
                docs = t.column("doc").to_numpy()
                cuts = [0, *(np.nonzero(docs[1:] != docs[:-1])[0] + 1).tolist()]
                found = [walk(t.slice(s, e - s)) for s, e in zip(cuts, cuts[1:])]
                if found:
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found)], ["doc", "n"])
                held = t.slice(cuts[-1])
        if held is not None:
            yield pa.RecordBatch.from_arrays([pa.array([c], pa.int64()) for c in walk(held)], ["doc", "n"])

    rows = pointer_table(nodes, layout).select("doc", "pre", "place", "first_child", "next_sibling")
    return rows.repartition("doc").sortWithinPartitions("doc", "place").mapInArrow(run, "doc long, n long")


def pointer_levels(nodes: DataFrame) -> DataFrame:
    """depth, n: nodes reached level by level over parent pointers."""
    edges = nodes.select("doc", "pre", "parent")
    level = edges.filter("parent = 0").select("doc", "pre")
    depth = nodes.agg(F.max("depth")).first()[0] or 0
    out = level.agg(F.lit(1).alias("depth"), F.count("*").alias("n"))
    for d in range(2, depth + 1):
        level = edges.join(level.select("doc", F.col("pre").alias("parent")), ["doc", "parent"]).select("doc", "pre")
        out = out.unionAll(level.agg(F.lit(d).alias("depth"), F.count("*").alias("n")))
    return out


def pointer_all_levels(nodes: DataFrame, folder: str) -> DataFrame:
    """depth, n: as ``pointer_levels``, but each level is written to ``folder`` and joined with once, until one is empty.

    The plan of a level does not hold those before it, so a chain of hundreds of levels can be walked."""
    spark = nodes.sparkSession
    edges = nodes.select("doc", "pre", "parent")
    level, out = edges.filter("parent = 0").select("doc", "pre"), []
    while True:
        path = f"{folder}/{len(out) + 1}"
        level.write.parquet(path)
        level = spark.read.schema("doc long, pre long").parquet(path)
        n = level.count()
        if not n:
            return spark.createDataFrame(out, "depth int, n long")
        out.append((len(out) + 1, n))
        level = edges.join(level.select("doc", F.col("pre").alias("parent")), ["doc", "parent"]).select("doc", "pre")


#: Rows of neighbouring fragments that are walked at a time, about.
WALK_ROWS = 200_000


def recurse_count(nodes: DataFrame) -> DataFrame:
    """n: elements counted by a walk over first children and next siblings of each document.

    A document with a spine is walked fragment by fragment, neighbours as one forest, and its spine by itself: a subtree that a task does not
    hold is counted by the task that does."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        total = 0

        def walk(t: pa.Table) -> int:
            pre, last = (t.column(c).to_numpy() for c in ("pre", "last"))
            after = np.searchsorted(pre, last, "right").tolist()
            elem = t.column("elem").to_numpy(zero_copy_only=False).tolist()
            n, i, up = 0, 0, [len(elem)]  # ends of the subtrees that are open
            while i < up[0]:
                n += elem[i]
                if after[i] > i + 1:
                    up.append(after[i])
                    i += 1  # first child
                    continue
                i = after[i]  # next sibling, or back to the last node above that has one
                while i == up[-1] and len(up) > 1:
                    up.pop()
            return n

        for batch in batches:
            if not batch.num_rows:
                continue
            t = pa.Table.from_batches([batch])
            t = t if held is None else pa.concat_tables([held, t])
            doc, frag = t.column("doc").to_numpy(), t.column("frag").to_numpy()
            heads = [0, *(np.nonzero((doc[1:] != doc[:-1]) | (frag[1:] != frag[:-1]))[0] + 1).tolist()]
            cuts = [0]
            for h in heads:
                if doc[h] != doc[cuts[-1]] or h - cuts[-1] > WALK_ROWS:
                    cuts.append(h)
            cuts.append(heads[-1])
            for s, e in zip(cuts, cuts[1:]):
                total += walk(t.slice(s, e - s))
            held = t.slice(heads[-1])
        if held is not None:
            total += walk(held)
        yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], ["n"])

    rows = nodes.select("doc", "frag", "pre", "last", (F.col("kind") == "elem").alias("elem"))
    return rows.repartition("doc", "frag").sortWithinPartitions("doc", "pre").mapInArrow(run, "n long").agg(F.sum("n").alias("n"))


def jump_loop(nodes: DataFrame, label: str) -> DataFrame:
    return nodes.filter((F.col("kind") == "elem") & (F.col("label") == label)).agg(F.count("*").alias("n"))


def label_paths(nodes: DataFrame) -> DataFrame:
    """doc, pre, path of every element: its labels from the root, for simple paths only."""
    e = nodes.filter("kind = 'elem'").select("doc", "pre", "parent", "depth", "label")
    level = e.filter("depth = 2").select("doc", "pre", F.concat(F.lit("/"), "label").alias("path"))
    out, depth = level, e.agg(F.max("depth")).first()[0] or 0
    for _ in range(3, depth + 1):
        level = e.join(level.select("doc", F.col("pre").alias("parent"), "path"), ["doc", "parent"]).select("doc", "pre", F.concat("path", F.lit("/"), "label").alias("path"))
        out = out.unionAll(level)
    return out


def simple_path(paths: DataFrame, path: str) -> DataFrame:
    """n of ``//a/b/c`` or ``/a/b``: a suffix test on label paths."""
    tail = path.removeprefix("//")
    hit = F.col("path").endswith("/" + tail) if path.startswith("//") else F.col("path") == path
    return paths.filter(hit).agg(F.count("*").alias("n"))


def dom_count(serialised: DataFrame, path: str) -> DataFrame:
    """n: Spark's own XPath over serialised documents, parsed row by row."""
    return serialised.agg(F.sum(F.expr(f"size(xpath(xml, '{path}'))")).cast("long").alias("n"))


