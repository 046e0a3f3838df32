"""Postings of q-grams: a candidate index whose answers are verified on the texts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Q = 3


def build_postings(texts: DataFrame, q: int = Q) -> DataFrame:
    """gram, text_id: the distinct q-grams of ``texts(text_id, value)``."""
    # characters as an array: a slice costs q, where a substring of UTF-8 would count from the start
    chars = texts.select("text_id", F.filter(F.split("value", ""), lambda c: c != "").alias("c"))
    at = F.when(F.size("c") >= q, F.sequence(F.lit(1), F.size("c") - (q - 1)))
    grams = F.array_distinct(F.transform(at, lambda i: F.concat(*[F.get("c", i + (k - 1)) for k in range(q)])))
    return chars.select("text_id", F.explode(grams).alias("gram"))


def candidates(postings: DataFrame, pattern: str, q: int = Q) -> DataFrame:
    """Texts that hold every q-gram of the pattern; patterns shorter than q have no candidates here and must be scanned."""
    grams = sorted({pattern[i : i + q] for i in range(len(pattern) - q + 1)})
    if not grams:
        raise ValueError(f"patterns of fewer than {q} characters cannot be looked up")
    return postings.filter(F.col("gram").isin(grams)).groupBy("text_id").agg(F.count("*").alias("n")).filter(F.col("n") == len(grams)).select("text_id")


def required_text(expression: str) -> str:
    """The longest string that every match of a regular expression holds, as far as its parts in a row tell; empty if none."""
    import re._parser as sre

    best, run = "", ""

    def walk(parts) -> None:
        nonlocal best, run
        for op, arg in parts:
            name = str(op)
            if name == "LITERAL":
                run += chr(arg)
                best = max(best, run, key=len)
                continue
            if name == "SUBPATTERN" and not arg[1] and not arg[2]:
                walk(arg[3])
                continue
            run = ""
            if name in ("MAX_REPEAT", "MIN_REPEAT", "POSSESSIVE_REPEAT") and arg[0] >= 1:
                walk(arg[2])  # once at least, but what follows need not be next to it
                run = ""

    parsed = sre.parse(expression)
    if not parsed.state.flags & 2:  # letters of either case stand for each other
        walk(parsed)
    return best


def contains(postings: DataFrame, texts: DataFrame, pattern: str, q: int = Q) -> DataFrame:
    """text_id of the texts that hold the pattern: candidates, then the texts themselves."""
    return texts.join(candidates(postings, pattern, q), "text_id", "left_semi").filter(F.col("value").contains(pattern)).select("text_id")
