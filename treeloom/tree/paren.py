"""The parentheses and label sequences of documents, from columns and back."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treeloom.tree.nav import close_position, open_position


def events(nodes: DataFrame) -> DataFrame:
    """doc, pos, open, label: opening and closing of every node."""
    a = nodes.select("doc", open_position().alias("pos"), F.lit(True).alias("open"), "label", "kind")
    return a.unionByName(nodes.select("doc", close_position().alias("pos"), F.lit(False).alias("open"), "label", "kind"))


def sequence(nodes: DataFrame) -> DataFrame:
    """doc, paren: the balanced parentheses of each document."""
    rows = events(nodes).groupBy("doc").agg(F.sort_array(F.collect_list(F.struct("pos", "open"))).alias("e"))
    return rows.select("doc", F.array_join(F.transform("e", lambda x: F.when(x["open"], F.lit("(")).otherwise(F.lit(")"))), "").alias("paren"))


def tag_sequence(nodes: DataFrame) -> DataFrame:
    """doc, tags: labels in the order of their opening and closing."""
    rows = events(nodes).groupBy("doc").agg(F.sort_array(F.collect_list(F.struct("pos", "open", "label"))).alias("e"))
    return rows.select("doc", F.array_join(F.transform("e", lambda x: F.concat(F.when(x["open"], F.lit("<")).otherwise(F.lit("/")), x["label"])), " ").alias("tags"))


def tag_entropy(nodes: DataFrame) -> DataFrame:
    """symbols, h: opening and closing labels of all documents, and their bits a symbol without context."""
    counts = events(nodes).groupBy("open", "label").agg(F.count("*").alias("n"))
    total = counts.agg(F.sum("n").alias("m"))
    # the total is one row
    return counts.crossJoin(F.broadcast(total)).agg(F.sum("n").alias("symbols"), F.round(F.sum(-F.col("n") * F.log2(F.col("n") / F.col("m"))) / F.sum("n"), 6).alias("h"))


def from_sequence(parens: DataFrame) -> DataFrame:
    """doc, pre, last, depth of every node, from doc and paren."""
    chars = parens.select("doc", F.posexplode(F.filter(F.split("paren", ""), lambda c: c != "")).alias("i", "c")).withColumn("step", F.when(F.col("c") == "(", 1).otherwise(-1))
    w = Window.partitionBy("doc").orderBy("i")
    rows = chars.withColumn("depth", F.sum("step").over(w)).withColumn("pre", F.sum(F.when(F.col("step") == 1, 1).otherwise(0)).over(w))
    # the closing of a node is the next position of its depth less one: partner by depth in order
    by_depth = rows.withColumn("level", F.when(F.col("step") == 1, F.col("depth")).otherwise(F.col("depth") + 1))
    pair = Window.partitionBy("doc", "level").orderBy("i")
    return by_depth.withColumn("last", F.lead("pre").over(pair)).filter("step = 1").select("doc", "pre", "last", F.col("depth").cast("int").alias("depth"))
