"""Connected components of an edge table by alternating star contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.runtime import is_empty, materialise


def components(edges: DataFrame, most: int = 60) -> DataFrame:
    """(id, component) for every end of `edges(a, b)`; component is the smallest id reachable.

    Each round hooks every vertex's larger neighbours, then its smaller ones, onto the least vertex seen. All steps
    are joins and partial minima, so a vertex with very many neighbours is never gathered in one task.
    An empty table gives an empty result; loops and repeated edges are harmless.
    """
    e = materialise(edges.select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).where("hi > lo").distinct())
    everyone = e.select(F.col("hi").alias("id")).union(e.select(F.col("lo").alias("id"))).distinct()
    for _ in range(most):
        both = e.union(e.select(F.col("lo").alias("hi"), F.col("hi").alias("lo")))  # hi: centre, lo: neighbour
        least = both.groupBy("hi").agg(F.min("lo").alias("m")).select("hi", F.least("hi", "m").alias("m"))
        large = both.where("lo > hi").join(least, "hi").where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo")).distinct()
        small_least = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(small_least, "hi")
        hooked = small.where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo")).union(small_least.select("hi", F.col("m").alias("lo")))
        nxt = materialise(hooked.where("hi <> lo").select(F.greatest("hi", "lo").alias("hi"), F.least("hi", "lo").alias("lo")).distinct())
        done = is_empty(nxt.join(nxt.select(F.col("hi").alias("lo")), "lo", "left_semi")) and is_empty(nxt.groupBy("hi").count().where("count > 1"))
        e = nxt
        if done:
            break
    else:
        raise RuntimeError("components didn't settle")
    return everyone.join(e.select(F.col("hi").alias("id"), "lo"), "id", "left").select("id", F.coalesce("lo", "id").alias("component"))
