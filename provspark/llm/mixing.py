"""Mixing sources to target weights by entropy balancing.

Each document has a rate r = min(cap, exp(t * size / mean size of its source)): the rates nearest in relative entropy to
one copy of everything, under a token constraint per source and the cap.  The convex dual separates by source; its
multipliers t are found by guarded Newton steps, each one distributed aggregation over the table of
(source, size, documents).  Rates become whole copies: errors are carried from the longest size to the shortest, and
within a size the documents of smallest hash take the copies over.

Null texts have size 0 and are taken once, which adds nothing; null sources are a source of their own.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD_PATTERN, stored

WEIGHTS, CAP = (5.0, 2.0, 1.0), 3.0
MOST_STEPS, TOLERANCE = 60, 1e-10
#: Documents ranked together within one (source, size).
RANKED_TOGETHER = 50_000


def sizes(docs: DataFrame, *carried: str) -> DataFrame:
    size = F.regexp_count(F.coalesce(F.col("text"), F.lit("")), F.lit(WORD_PATTERN)).cast("long")
    key = F.when(F.col("source").isNull(), F.lit("")).otherwise(F.concat(F.lit("="), F.col("source").cast("string")))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), key.alias("key"), size.alias("size"), *carried)


def targets(sized: DataFrame, weights=WEIGHTS, cap: float = CAP) -> DataFrame:
    """key, source_size, target: weights in turn over the sources by code point (null last), excess over the cap reshared."""
    by = Window.orderBy(F.col("key") == "", "key")
    share = F.element_at(F.array(*map(F.lit, weights)), (F.row_number().over(by) - 1) % len(weights) + 1)
    sources = stored(sized.groupBy("key").agg(F.sum("size").alias("source_size")).withColumn("weight", share), "sources")
    total, weight = sources.agg(F.sum("source_size"), F.sum("weight")).first()
    level, capped, most = (total or 0) / (weight or 1), -1, cap * F.col("source_size")
    while True:
        over = F.col("weight") * F.lit(level) > most
        n, full, free = sources.agg(F.sum(over.cast("long")), F.sum(F.when(over, most)), F.sum(F.when(~over, F.col("weight")))).first()
        if not n or n == capped or not free:
            break
        capped, level = n, (total - full) / free
    return sources.select("key", "source_size", F.least(most, F.col("weight") * F.lit(level)).cast("double").alias("target"))


def rates(cells: DataFrame, goals: DataFrame, cap: float = CAP) -> DataFrame:
    """cells (key, size, n) with ``rate``; the dual's multiplier of each source by guarded Newton iterations."""
    state = goals.join(cells.groupBy("key").agg((F.sum(F.col("size") * F.col("n")) / F.sum("n")).alias("mean")), "key")
    fixed = F.when(F.col("target") <= 0, F.lit(0.0)).when(F.col("target") >= cap * F.col("source_size") * (1 - 1e-12), F.lit(cap))
    state = stored(state.select("key", "target", "mean", fixed.alias("fixed"), F.lit(0.0).alias("t"), F.lit(-1e9).alias("low"), F.lit(1e9).alias("high")), "dual")
    rate = F.least(F.lit(cap), F.exp(F.least(F.lit(50.0), F.col("t") * F.col("size") / F.col("mean"))))
    for _ in range(MOST_STEPS):
        tilted = cells.join(state, "key").where("fixed is null").withColumn("rate", rate)
        tokens = F.col("n") * F.col("size") * F.col("rate")
        sums = tilted.groupBy("key").agg(F.sum(tokens).alias("got"), F.sum(F.when(F.col("rate") < cap, tokens * F.col("size") / F.col("mean"))).alias("slope"))
        moved = state.join(sums, "key", "left")
        low = F.when(F.col("got") < F.col("target"), F.col("t")).otherwise(F.col("low"))
        high = F.when(F.col("got") > F.col("target"), F.col("t")).otherwise(F.col("high"))
        # Newton on the logarithm of the constraint: steps stay right when the rates are far from the target
        step = F.col("t") + F.log(F.col("target") / F.col("got")) * F.col("got") / F.col("slope")
        middle = F.when(F.col("low") < -1e8, 2 * F.col("t") - 1).when(F.col("high") > 1e8, 2 * F.col("t") + 1).otherwise((F.col("low") + F.col("high")) / 2)
        moved = moved.withColumn("low", low).withColumn("high", high)
        moved = moved.withColumn("step", step).withColumn("t", F.when(F.col("got").isNull(), F.col("t")).when((F.col("step") > F.col("low")) & (F.col("step") < F.col("high")), F.col("step")).otherwise(middle))
        moved = stored(moved.withColumn("off", F.abs(F.col("got") / F.col("target") - 1)).select(*state.columns, "off"), "dual")
        worst = moved.agg(F.max("off")).first()[0]
        state = moved.drop("off")
        if worst is None or worst < TOLERANCE:
            break
    return cells.join(state, "key").withColumn("rate", F.coalesce("fixed", F.when(F.col("size") == 0, F.lit(1.0)), rate)).select("key", "size", "n", "rate")



def _whole_source(cells: pd.DataFrame) -> pd.DataFrame:
    """Copies of each size of one source: from the longest size on, what rounding left over goes to the next."""
    cells = cells.sort_values("size", ascending=False, kind="stable")
    out, carry = np.zeros(len(cells), np.int64), 0.0
    for i, (size, n, rate) in enumerate(zip(cells["size"].tolist(), cells["n"].tolist(), cells["rate"].tolist(), strict=True)):
        least, most = int(np.floor(rate)) * n, int(np.ceil(rate)) * n
        wish = rate * n if size == 0 else rate * n + carry / size
        out[i] = min(max(round(wish), least), most)
        carry += (rate * n - out[i]) * size
    return cells[["key", "size", "n"]].assign(copies=out)


def _dealt(rows: DataFrame, sized: DataFrame, weights, cap: float) -> DataFrame:
    """``rows`` of ``sizes`` with source_size, target, copies; ``sized`` are the same rows as a scratch table."""
    goals = stored(targets(sized, weights, cap), "targets")
    cells = stored(sized.groupBy("key", "size").agg(F.count("*").alias("n")), "cells")
    whole = rates(cells, goals, cap).groupBy("key").applyInPandas(_whole_source, "key string, size long, n long, copies long")
    whole = stored(whole, "whole")
    chunks = (cells.agg(F.max("n")).first()[0] or 0) // RANKED_TOGETHER + 1
    salt = lambda df: df.withColumn("chunk", F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(chunks)))
    inside = Window.partitionBy("key", "size", "chunk").orderBy(F.xxhash64("doc_id", F.lit(2)), "doc_id")
    before = salt(sized).groupBy("key", "size", "chunk").agg(F.count("*").alias("here"))
    before = before.withColumn("before", F.coalesce(F.sum("here").over(Window.partitionBy("key", "size").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    share = before.join(whole, ["key", "size"]).select("key", "size", "chunk", "before", F.expr("copies div n").alias("each"), F.expr("copies % n").alias("extra"))
    ranked = salt(rows).withColumn("rank", F.row_number().over(inside)).join(share, ["key", "size", "chunk"])
    taken = ranked.withColumn("copies", F.col("each") + F.when(F.col("rank") + F.col("before") <= F.col("extra"), 1).otherwise(0)).drop("chunk", "rank", "before", "each", "extra")
    return taken.join(F.broadcast(goals) if goals.count() < 100_000 else goals, "key")


def copies(docs: DataFrame, weights=WEIGHTS, cap: float = CAP) -> DataFrame:
    """doc_id, key, size, source_size, target, copies - one row per row of docs; the same on every run.

    Rows without a doc_id take part like any other; rows that share one are dealt their copies one by one.
    """
    sized = stored(sizes(docs), "sizes")
    return _dealt(sized, sized, weights, cap).select("doc_id", "key", "size", "source_size", "target", "copies")


def mixed(docs: DataFrame, weights=WEIGHTS, cap: float = CAP) -> DataFrame:
    """The mix itself: each row as often as it is taken, with the columns of docs, whatever their names."""
    rows = sizes(docs.select("doc_id", "text", "source", F.struct("*").alias("_document")), "_document")
    taken = _dealt(rows, stored(rows.drop("_document"), "sizes"), weights, cap).where("copies > 0")
    return taken.select("_document", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("_copy")).select("_document.*")
