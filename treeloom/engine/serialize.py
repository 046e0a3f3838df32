"""Results as markup: well formed, escaped, in document order."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treeloom.sources.trees import Tree


def escaped(text: Column, quote: bool = False) -> Column:
    out = F.replace(F.replace(F.replace(text, F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;")), F.lit(">"), F.lit("&gt;"))
    return F.replace(out, F.lit('"'), F.lit("&quot;")) if quote else out


def markup_events(tree: Tree) -> DataFrame:
    """doc, frag, pre, pos, piece: the pieces of markup of every element and text, with their places."""
    attrs = tree.all.filter("kind = 'attr'").groupBy("doc", F.col("host").alias("pre")).agg(
        F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("ord", "label", "value"))), lambda a: F.concat(F.lit(" "), a["label"], F.lit('="'), escaped(a["value"], True), F.lit('"'))), "").alias("attrs")
    )
    place = 2 * F.col("pre") - F.col("depth")
    elems = tree.nodes.filter("kind = 'elem'").select("doc", "frag", "pre", "last", "depth", "label").join(attrs, ["doc", "pre"], "left")
    opening = elems.select("doc", "frag", "pre", place.alias("pos"), F.concat(F.lit("<"), "label", F.coalesce("attrs", F.lit("")), F.lit(">")).alias("piece"))
    closing = elems.select("doc", "frag", "pre", (place + 2 * (F.col("last") - F.col("pre") + 1) - 1).alias("pos"), F.concat(F.lit("</"), "label", F.lit(">")).alias("piece"))
    texts = tree.all.filter("kind = 'text'").select("doc", "frag", "pre", place.alias("pos"), escaped(F.col("value")).alias("piece"))
    return opening.unionByName(closing).unionByName(texts)


def subtrees(tree: Tree, results: DataFrame) -> DataFrame:
    """doc, pre, xml of every result (doc, pre, last); results lie inside one fragment each."""
    frag = tree.nodes.select("doc", "pre", "frag")
    asked = results.select("doc", "pre", "last").join(frag, ["doc", "pre"]).select("doc", "frag", F.col("pre").alias("top"), F.col("last").alias("end"))
    inside = markup_events(tree).join(asked, ["doc", "frag"]).filter(F.col("pre").between(F.col("top"), F.col("end")))
    joined = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("pos", "piece"))), lambda x: x["piece"]), "")
    return inside.groupBy("doc", F.col("top").alias("pre")).agg(joined.alias("xml"))


def spine_pieces(tree: Tree, results: list[tuple]) -> DataFrame:
    """doc, pre, at, xml: the pieces of markup that nodes above all fragments have in results (doc, pre, last) among them."""
    asked = tree.spark.createDataFrame(results, "doc long, top long, end long")
    spine = tree.all.filter("frag = -1")
    attrs = tree.all.filter("frag <> -1 and kind = 'attr'").join(F.broadcast(spine.select("doc", F.col("pre").alias("host"))), ["doc", "host"], "left_semi")
    inside = markup_events(Tree(tree.spark, spine.unionByName(attrs))).filter("frag = -1").join(F.broadcast(asked), "doc").filter(F.col("pre").between(F.col("top"), F.col("end")))
    return inside.select("doc", F.col("top").alias("pre"), F.col("pos").cast("long").alias("at"), F.col("piece").alias("xml"))
