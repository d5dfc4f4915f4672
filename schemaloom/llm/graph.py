"""Connected components over tables, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from schemaloom.llm.shared import Scratch


def components(edges: DataFrame, scratch: Scratch, most_rounds: int = 64) -> DataFrame:
    """(node, component) of every node that has an edge; edges: (a, b) of 64-bit integers, any order, repeats allowed.
    A component's name is its smallest node.

    Each round links every node's larger neighbours, then its smaller ones, to the smallest node around it, until all
    stars stand still; rounds grow with the logarithm of a component's width. Minima are summed before the shuffle and
    written, so that the join with the edges can split a hub's rows among tasks. Nothing but two sums reaches the
    driver.
    """
    distinct = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    now = scratch.table("edges-0", distinct)
    seen = None
    for k in range(1, most_rounds + 1):
        both = now.union(now.select("v", "u"))
        around = scratch.table(f"around-{k}", both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")))
        large = both.join(around, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = scratch.table(f"large-{k}", large)
        least = scratch.table(f"least-{k}", large.groupBy("u").agg(F.min("v").alias("m")))
        small = large.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", "m")).distinct()
        after = scratch.table(f"edges-{k}", small)
        sign = after.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        scratch.drop(f"around-{k}", f"large-{k}", f"least-{k}", f"edges-{k - 1}")
        now = after
        if sign == seen:
            break
        seen = sign
    else:
        raise RuntimeError(f"components did not settle in {most_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(now.select("v", "v").distinct())
