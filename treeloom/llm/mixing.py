"""Temperature mixing of sources, with DataFrame functions only.

A source's weight is its share of all tokens to the power of an exponent, normalised.  The exponent is found by
bisection: the largest that reaches a target entropy, or the smallest for which no source is repeated more often
than a limit.  A budget of tokens times the weight gives each source its own budget.  Sources may be any number: they stay a
table, of which the driver gets sums for the exponents of one round of bisection at a time.

A source's budget is spent in passes over its documents.  A pass is a permutation of blocks and of the documents
within them: the order of a seeded hash of (pass, doc_id), whose leading bits are the block.  All passes but the last
are whole; the last takes documents in its order as long as their sum stays within what is left.  Where it ends is found
on block sums first and then inside the one block it ends in, so that no task sees more than a block of one source.
Each document then only compares its hash with the end of its source.

``mix_at``, from 0 to 1, is how far through its source's budget a row stands.  Rows in the order of ``mix_at`` are the mixture: every
prefix of that order has the target weights, up to the spread of a hash.

A token is a word (maximal run of characters other than blank and \\x09-\\x0D).  Null texts have none; null sources are one
source of their own; repeated rows are separate documents with one order.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from treeloom.llm.store import fresh, keyed_join, saved

#: Documents that a block of a pass has, about; blocks are a power of two, at most 2^MAX_BITS a source and pass.
BLOCK_ROWS = 4096
MAX_BITS = 20


@dataclass(frozen=True)
class Weights:
    exponent: float
    shares: list[float]
    weights: list[float]


def weigh(tokens: list[int], exponent: float) -> Weights:
    total = sum(tokens) or 1
    shares = [t / total for t in tokens]
    raw = [s**exponent if s else 0.0 for s in shares]
    norm = sum(raw) or 1.0
    return Weights(exponent, shares, [r / norm for r in raw])


def entropy(weights: list[float]) -> float:
    return -sum(w * math.log(w) for w in weights if w > 0)


def repetition(w: Weights) -> float:
    """Most passes over a source, for one pass over the source that is passed least."""
    passes = [x / s for x, s in zip(w.weights, w.shares) if s]
    return max(passes) / min(passes) if passes else 1.0


def bisect_exponent(tokens: list[int], target_entropy: float | None = None, max_repetition: float | None = None, steps: int = 60) -> Weights:
    """Entropy falls and repetition falls as the exponent grows from 0 (even weights) to 1 (natural shares)."""
    low, high = 0.0, 1.0
    for _ in range(steps):
        mid = (low + high) / 2
        w = weigh(tokens, mid)
        if target_entropy is not None:
            # the largest exponent that still reaches the entropy
            low, high = (mid, high) if entropy(w.weights) >= target_entropy else (low, mid)
        else:
            # the smallest exponent that keeps within the limit
            low, high = (low, mid) if repetition(w) <= max_repetition else (mid, high)
    return weigh(tokens, low if target_entropy is not None else high)


def word_count(text: Column) -> Column:
    """Words of a text; a blank before each run, then blanks are counted."""
    runs = F.regexp_replace(F.coalesce(text, F.lit("")), r"[^\x20\x09-\x0D]+", "x")
    return F.length(F.regexp_replace(runs, r"[\x20\x09-\x0D]+", "")).cast("long")


def _order(seed: int, epoch: Column, doc_id: Column) -> Column:
    return F.xxhash64(F.lit(seed), epoch, doc_id)


def _block(order: Column, bits: int) -> Column:
    """Leading bits of the hash, signed, so that blocks follow the order of the hash."""
    return (F.shiftright(order, 64 - bits) if bits else F.lit(0)).cast("int")


#: Exponents whose sums are taken in one round: five halvings of the interval.
POINTS = 31


def find_exponent(shares: DataFrame, target_entropy: float | None, max_repetition: float | None, steps: int = 60) -> float:
    """The exponent of :func:`bisect_exponent` for a table of positive ``share``s, by rounds of ``POINTS`` exponents at once."""
    if max_repetition is not None:
        # passes go with share^(exponent - 1): only the least and the greatest share count
        r = shares.agg(F.min("share").alias("lo"), F.max("share").alias("hi")).first()
        if r["lo"] is None:
            return 1.0
        return bisect_exponent([r["lo"], r["hi"]], max_repetition=max_repetition, steps=steps).exponent
    low, high = 0.0, 1.0
    for _ in range(-(-steps // 5)):
        points = [low + (high - low) * (i + 1) / (POINTS + 1) for i in range(POINTS)]
        raw = [F.pow("share", F.lit(a)) for a in points]
        sums = shares.agg(*[F.sum(x).alias(f"z{i}") for i, x in enumerate(raw)], *[F.sum(x * F.log("share")).alias(f"l{i}") for i, x in enumerate(raw)]).first()
        if sums["z0"] is None:
            return 1.0
        # entropy of weights share^a / z: ln z - a * sum(share^a ln share) / z, falling in a
        reached = [math.log(sums[f"z{i}"]) - a * sums[f"l{i}"] / sums[f"z{i}"] >= target_entropy for i, a in enumerate(points)]
        k = sum(reached)
        low, high = ([low, *points][k], [*points, high][k])
        if high - low < 2.0**-steps:
            break
    return low


@dataclass(frozen=True)
class Plan:
    """``rows``: a table of source, key, tokens, n, weight, exponent, whole (passes) and end, the hash of the last document of the partial
    pass, null if it takes none.  ``bits``: 2^bits blocks a pass of the largest source."""

    rows: DataFrame
    bits: int
    total: int


#: Null is a source of its own.
def _key(source: str = "source") -> Column:
    return F.when(F.col(source).isNull(), F.lit("n")).otherwise(F.concat(F.lit("s"), F.col(source).cast("string")))


def mixing_plan(counted: DataFrame, seed: int, target_entropy: float | None, max_repetition: float | None, budget: int | None) -> Plan:
    """Budgets of the sources of the saved table ``counted(source, doc_id, tokens)``."""
    sums = counted.withColumn("key", _key()).groupBy("key").agg(F.first("source").alias("source"), F.coalesce(F.sum("tokens"), F.lit(0)).alias("tokens"), F.count("*").alias("n"))
    sums = saved(sums, "sources", few_files=True)
    whole = sums.agg(F.sum("tokens").alias("t"), F.max("n").alias("largest"), F.sum("n").alias("n")).first()
    total = whole["t"] or 1
    bits = min(MAX_BITS, max(0, math.ceil(math.log2(max(1, whole["largest"] or 0) / BLOCK_ROWS))))
    shares = sums.withColumn("share", F.col("tokens") / F.lit(float(total)))
    exponent = find_exponent(shares.filter("tokens > 0"), target_entropy, max_repetition)
    shares = shares.withColumn("raw", F.when(F.col("tokens") > 0, F.pow("share", F.lit(exponent))).otherwise(0.0))
    norm = shares.agg(F.sum("raw")).first()[0] or 1.0
    shares = shares.withColumn("weight", F.col("raw") / F.lit(norm))
    if budget is None:
        # the least budget that passes every source once or more
        budget = shares.filter("weight > 0").agg(F.max(F.col("tokens") / F.col("weight"))).first()[0] or 0
    own = F.col("weight") * F.lit(float(budget))
    passes = F.when(F.col("tokens") > 0, F.floor(own / F.col("tokens") + 1e-9)).otherwise(1).cast("int")
    rest = F.when(F.col("tokens") > 0, F.greatest(F.lit(0), F.floor(own - F.col("whole") * F.col("tokens")))).otherwise(0).cast("long")
    plan = shares.withColumn("whole", passes).withColumn("rest", rest).select("key", "source", "tokens", "n", "weight", F.lit(exponent).alias("exponent"), "whole", "rest")
    plan = saved(plan, "plan", few_files=True)
    partial = keyed_join(counted.select(_key().alias("key"), "tokens", "doc_id"), plan.filter("rest > 0").select("key", "whole", "rest", "n"), ["key"], "n", whole["n"] or 0)
    partial = partial.select("key", "tokens", "rest", _order(seed, F.col("whole"), F.col("doc_id")).alias("o")).withColumn("b", _block(F.col("o"), bits))
    # at most 2^MAX_BITS sums a source; the one block in which a source's budget runs out is known after this
    blocks = partial.groupBy("key", "b", "rest").agg(F.sum("tokens").alias("t"))
    before = F.sum("t").over(Window.partitionBy("key").orderBy("b")) - F.col("t")
    cuts = saved(blocks.withColumn("before", before).filter("before <= rest and before + t > rest").select("key", "b", (F.col("rest") - F.col("before")).alias("room")), "cuts", few_files=True)
    # rows of one order (repeated ids) are taken or left together
    steps = partial.join(cuts, ["key", "b"]).groupBy("key", "room", "o").agg(F.sum("tokens").alias("t"))
    upto = F.sum("t").over(Window.partitionBy("key").orderBy("o"))
    ends = steps.withColumn("upto", upto).filter("upto <= room").groupBy("key").agg(F.max("o").alias("last"))
    # no document of the block in which the pass ends fits: it ends just before that block
    start = F.shiftleft(F.col("b").cast("long"), 64 - bits) if bits else F.lit(-(1 << 63))
    before_block = F.when(start > -(1 << 63), start - 1)
    end = F.coalesce("last", F.when(F.col("b").isNotNull(), before_block).when(F.col("rest") > 0, F.lit((1 << 63) - 1)))
    out = plan.join(cuts.select("key", "b"), "key", "left").join(ends, "key", "left").withColumn("end", end).drop("b", "last", "rest")
    return Plan(saved(out, "ends", few_files=True), bits, whole["n"] or 0)


def counted_documents(docs: DataFrame) -> DataFrame:
    """source, doc_id and tokens of every document, saved: texts are read once."""
    return saved(docs.select("source", "doc_id", word_count(F.col("text")).alias("tokens")), "tokens")


MADE = ("epoch", "mix_order", "mix_at", "weight", "exponent")


def spread(docs: DataFrame, plan: Plan, seed: int) -> DataFrame:
    """Rows of ``docs(source, doc_id, ...)`` as often as ``plan`` takes them; those of frequent sources are copied where they lie."""
    keep = [c for c in docs.columns if c.lower() not in MADE]
    key, n, w, a, whole, end, e = fresh([*docs.columns, *MADE], "key", "n", "w", "a", "whole", "end", "e")
    rows = docs.select(*[F.col(f"`{c}`") for c in keep], _key().alias(key))
    frame = plan.rows.select(*[F.col(x).alias(y) for x, y in (("key", key), ("n", n), ("weight", w), ("exponent", a), ("whole", whole), ("end", end))])
    joined = keyed_join(rows, frame, [key], n, plan.total)
    extra = F.coalesce(_order(seed, F.col(whole), F.col("doc_id")) <= F.col(end), F.lit(False)).cast("int")
    passes = F.col(whole) + extra
    unit = lambda c: (c.cast("double") + 2.0**63) / 2.0**64
    order = _order(seed, F.col(e), F.col("doc_id"))
    budget = F.col(whole) + F.coalesce(unit(F.col(end)), F.lit(0.0))
    return (
        joined.withColumn(e, F.explode(F.when(passes > 0, F.sequence(F.lit(0), passes - 1)).otherwise(F.array().cast("array<int>"))))
        .select(*[F.col(f"`{c}`") for c in keep], F.col(e).alias("epoch"), order.alias("mix_order"), ((F.col(e) + unit(order)) / budget).alias("mix_at"), F.col(w).alias("weight"), F.col(a).alias("exponent"))
    )


def mix_sources(docs: DataFrame, target_entropy: float | None = None, max_repetition: float | None = None, budget: int | None = None, seed: int = 0) -> DataFrame:
    """Rows of ``docs`` as often as the mixture takes them, with ``epoch`` (the pass, from 0), ``mix_order`` (the order in the
    pass), ``mix_at`` (the order in the mixture), ``weight`` and ``exponent``.

    Give one of ``target_entropy`` and ``max_repetition``.  Without a ``budget`` every document is taken at least
    once.  Of frequent sources nothing but block sums is shuffled.
    """
    if (target_entropy is None) == (max_repetition is None):
        raise ValueError("give either target_entropy or max_repetition")
    return spread(docs, mixing_plan(counted_documents(docs), seed, target_entropy, max_repetition, budget), seed)


def mix_index(docs: DataFrame, target_entropy: float | None = None, max_repetition: float | None = None, budget: int | None = None, seed: int = 0) -> DataFrame:
    """The mixture without texts: source, doc_id, tokens and the columns of :func:`mix_sources`, with ``block`` and ``position``
    (gapless from 0 in each source and pass)."""
    counted = counted_documents(docs)
    plan = mixing_plan(counted, seed, target_entropy, max_repetition, budget)
    rows = spread(counted, plan, seed).withColumn("block", _block(F.col("mix_order"), plan.bits)).withColumn("key", _key())
    unit = ["key", "epoch", "block"]
    sizes = rows.groupBy(*unit).agg(F.count("*").alias("n"))
    first = F.sum("n").over(Window.partitionBy("key", "epoch").orderBy("block")) - F.col("n")
    offsets = sizes.select(*unit, first.alias("first"))
    placed = rows.withColumn("r", F.row_number().over(Window.partitionBy(*unit).orderBy("mix_order", "doc_id")) - 1)
    return placed.join(offsets, unit).withColumn("position", (F.col("first") + F.col("r")).cast("long")).drop("key", "r", "first")
