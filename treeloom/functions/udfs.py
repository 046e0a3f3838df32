"""Functions usable from SQL: a path over one markup string, a parser as a table function, a collecting aggregate."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from treeloom.automaton.compile import to_automaton
from treeloom.automaton.evaluate import Counters, Document, Runner
from treeloom.automaton.jump import Jumper
from treeloom.baselines.engines import _holds, document_of
from treeloom.sources.html import parse_html
from treeloom.tree.encode import flatten
from treeloom.xpath.parser import parse


def path_count(path: str):
    """Column function: results of ``path`` in a page of markup, by an automaton run on each row."""
    automaton = to_automaton(parse(path))

    @pandas_udf("long")
    def run(pages: pd.Series) -> pd.Series:
        runner = Runner(automaton)
        out = []
        for html in pages:
            doc, values, parents = document_of(parse_html(html))
            doc.flags = [_holds(p, doc, values, parents) for p in automaton.preds]
            out.append(runner.count(doc, runner.run(doc, Counters())))
        return pd.Series(out, dtype="int64")

    return run


_NODE = T.StructType([T.StructField(n, t) for n, t in (("pre", T.LongType()), ("last", T.LongType()), ("depth", T.IntegerType()), ("parent", T.LongType()), ("label", T.StringType()), ("kind", T.StringType()), ("value", T.StringType()))])


@udtf(returnType=_NODE)
class ParseTree:
    """Nodes of a page of markup, one row each."""

    def eval(self, html: str):
        for pre, last, depth, parent, _, label, kind, _, value in flatten(parse_html(html)):
            yield pre, last, depth, parent, label, kind, value


@udtf(returnType=T.StructType([T.StructField(n, T.LongType()) for n in ("doc", "pre", "last")]))
class PathQuery:
    """Results of a path in node tables: ``path_query(TABLE(nodes) PARTITION BY (doc) ORDER BY (pre), '//a//b')``.

    Rows have doc, pre, last, parent, label, kind and value; a document is one partition and is run when its last row is in."""

    def __init__(self):
        self.rows: list = []
        self.path: str | None = None

    def eval(self, row, path: str):
        self.path = path
        self.rows.append((row["pre"], row["last"], row["parent"], row["label"], row["kind"], row["value"], row["doc"]))

    def terminate(self):
        if not self.rows:
            return
        automaton = to_automaton(parse(self.path))
        pre, last, parent, labels, kinds, values, docs = zip(*self.rows)
        doc = Document(*(np.array(x) for x in (pre, last, parent)), list(labels), list(kinds), [])
        doc.flags = [_holds(p, doc, list(values), list(parent)) for p in automaton.preds]
        runner = Jumper(automaton) if Jumper.fits(automaton) else Runner(automaton)
        for i in runner.nodes_of(doc, runner.run(doc, Counters())):
            yield docs[0], pre[i], last[i]


@udtf(returnType=T.StructType([T.StructField("position", T.IntegerType())]))
class Locate:
    """Positions (from 1) of a pattern in a text, overlapping ones too."""

    def eval(self, text: str, pattern: str):
        at = text.find(pattern) if text and pattern else -1
        while at >= 0:
            yield (at + 1,)
            at = text.find(pattern, at + 1)


@pandas_udf(T.StringType())
def first_by_length(values: pd.Series) -> str:
    """Aggregate: the longest string, the first in order among equals."""
    found = [v for v in values if v is not None]
    return min(found, key=lambda v: (-len(v), v)) if found else None


def register_functions(spark: SparkSession) -> None:
    spark.udtf.register("parse_tree", ParseTree)
    spark.udtf.register("locate_all", Locate)
    spark.udtf.register("path_query", PathQuery)
    spark.udf.register("longest_string", first_by_length)
    spark.udf.register("count_links", path_count("//a"))
