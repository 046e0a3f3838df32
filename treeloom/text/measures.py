"""Entropy, first-column counts and runs of a text collection, as aggregations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def characters(texts: DataFrame) -> DataFrame:
    """text_id, i (from 1), c of every character of ``texts(text_id, value)``."""
    split = F.filter(F.split("value", ""), lambda c: c != "")
    return texts.select("text_id", F.posexplode(split).alias("i", "c")).withColumn("i", F.col("i") + 1)


def entropy(texts: DataFrame, k: int = 0) -> DataFrame:
    """h: bits a character given the ``k`` characters before it in the text."""
    rows = characters(texts)
    if k:
        w = Window.partitionBy("text_id").orderBy("i")
        rows = rows.withColumn("ctx", F.concat_ws("", *[F.lag("c", j).over(w) for j in range(k, 0, -1)])).filter(F.col("i") > k)
    else:
        rows = rows.withColumn("ctx", F.lit(""))
    pairs = rows.groupBy("ctx", "c").agg(F.count("*").alias("n"))
    whole = pairs.groupBy("ctx").agg(F.sum("n").alias("m"))
    return pairs.join(whole, "ctx").agg(F.round(F.sum(-F.col("n") * F.log2(F.col("n") / F.col("m"))) / F.sum("n"), 6).alias("h"))


def symbol_starts(texts: DataFrame) -> DataFrame:
    """c, n, smaller: characters that sort before c in all texts together (the first-column table)."""
    counts = characters(texts).groupBy("c").agg(F.count("*").alias("n"))
    # one row a symbol: the alphabet bounds this window
    return counts.withColumn("smaller", F.sum("n").over(Window.orderBy("c").rowsBetween(Window.unboundedPreceding, -1))).fillna(0, ["smaller"])


def store_offsets(texts: DataFrame, part_rows: int = 1 << 16) -> DataFrame:
    """text_id, start: where each text begins in the plain store, by sums of id ranges and sums inside a range."""
    rows = texts.select("text_id", (F.octet_length("value") + 1).alias("n"), F.floor(F.col("text_id") / part_rows).alias("p"))
    parts = rows.groupBy("p").agg(F.sum("n").alias("s"))
    before = parts.withColumn("before", F.sum("s").over(Window.orderBy("p")) - F.col("s")).drop("s")
    inside = F.sum("n").over(Window.partitionBy("p").orderBy("text_id")) - F.col("n")
    return rows.withColumn("inside", inside).join(before, "p").select("text_id", (F.col("before") + F.col("inside")).alias("start"))
