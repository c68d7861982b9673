"""The part of a graph that can hold an occurrence: edges on fewer triangles than every edge of the pattern are no image of one."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from coverdp.model import TargetGraph
from coverdp.operators.dp_local import label_masks
from coverdp.patterns import Pattern
from coverdp.runtime import materialise

#: Triangles that one task peels; more are peeled by joins.
LOCAL_TRIANGLES = 4_000_000
#: Rounds of joins; any number of them leaves all occurrences whole.
ROUNDS = 24
#: Ids that a join sends to every task.
LOCAL_IDS = 1_000_000


def support(pattern: Pattern) -> int:
    """The triangles that each edge of the pattern lies on, at least."""
    return min((len(pattern.neighbours[a] & pattern.neighbours[b]) for a, b in pattern.edges), default=0)


def triangles(g: TargetGraph) -> DataFrame:
    """x < y < z of every triangle; pairs are made at the end of lower degree, so a hub pairs few of its neighbours."""
    e = g.edges.select("src", "dst")
    degree = materialise(g.degrees())
    side = lambda end: degree.select(F.col("id").alias(end), F.col("degree").alias(f"{end}_degree"))
    up = F.struct("src_degree", "src") < F.struct("dst_degree", "dst")
    arcs = e.join(side("src"), "src").join(side("dst"), "dst").select(F.when(up, F.col("src")).otherwise(F.col("dst")).alias("low"), F.when(up, F.col("dst")).otherwise(F.col("src")).alias("high"))
    arcs = materialise(arcs)
    pairs = arcs.join(arcs.select("low", F.col("high").alias("other")), "low").where("high < other")
    closed = pairs.join(e.select(F.col("src").alias("high"), F.col("dst").alias("other")), ["high", "other"])
    corner = F.array_sort(F.array("low", "high", "other"))
    return closed.select(*(corner[i].alias(c) for i, c in enumerate("xyz")))


def _sides(t: DataFrame) -> DataFrame:
    return t.select("x", "y", "z", F.explode(F.array(*(F.struct(F.col(a).alias("src"), F.col(b).alias("dst")) for a, b in ("xy", "xz", "yz")))).alias("e")).select("x", "y", "z", "e.src", "e.dst")


def _peel(least: int):
    def run(table: pa.Table) -> pa.Table:
        corners = np.stack([np.asarray(table[c]) for c in "xyz"], axis=1)
        ids, at = np.unique(corners, return_inverse=True)
        at = at.reshape(corners.shape)
        code, side = np.unique(np.stack([at[:, a] * len(ids) + at[:, b] for a, b in ((0, 1), (0, 2), (1, 2))], axis=1), return_inverse=True)
        side = side.reshape(corners.shape)
        while len(side):
            held = np.bincount(side.ravel(), minlength=len(code)) >= least
            whole = held[side].all(axis=1)
            if whole.all():
                break
            side = side[whole]
        left = code[np.unique(side)]
        return pa.table({"src": ids[left // max(1, len(ids))], "dst": ids[left % max(1, len(ids))]})

    return run


def _labelled(g: TargetGraph, pattern: Pattern) -> TargetGraph:
    """g without vertices that fit no pattern vertex by their own label and their neighbours', and edges that fit no pattern edge."""
    near = [sum(1 << q for q in nb) for nb in pattern.neighbours]
    masks = materialise(label_masks(g.vertices, pattern).where("mask > 0").select("id", F.col("mask").cast("long").alias("mask")))
    arcs = g.arcs.select(F.col("src").alias("id"), F.col("dst").alias("other"))
    total = lambda m: m.agg(F.sum(F.bit_count("mask"))).first()[0]
    left = total(masks)
    for _ in range(pattern.k):
        met = arcs.join(masks.select(F.col("id").alias("other"), F.col("mask").alias("near")), "other").groupBy("id").agg(F.bit_or("near").alias("near"))
        both = masks.join(met, "id", "left").select("id", "mask", F.coalesce("near", F.lit(0).cast("long")).alias("near"))
        fits = [F.when(F.col("mask").bitwiseAND(1 << p).cast("boolean") & (F.col("near").bitwiseAND(n) == n), F.lit(1 << p)).otherwise(0) for p, n in enumerate(near)]
        masks = materialise(both.select("id", sum(fits[1:], fits[0]).cast("long").alias("mask")).where("mask > 0"))
        before, left = left, total(masks)
        if left == before:
            break
    side = lambda end: masks.select(F.col("id").alias(end), F.col("mask").alias(f"{end}_mask"))
    ends = g.edges.join(side("src"), "src").join(side("dst"), "dst")
    has = lambda end, p: F.col(f"{end}_mask").bitwiseAND(1 << p) > 0
    fit = F.lit(False)
    for a, b in pattern.edges:
        fit = fit | (has("src", a) & has("dst", b)) | (has("src", b) & has("dst", a))
    return TargetGraph(materialise(g.vertices.join(masks, "id", "left_semi")), materialise(ends.where(fit).select("src", "dst")))


def _alike(g: TargetGraph) -> TargetGraph:
    """The edges at whose one end some other edge leads to an equal label (by hash, so a few more may stay)."""
    label = g.vertices.where("label is not null").select(F.col("id").alias("dst"), F.xxhash64("label").alias("label"))
    met = g.arcs.join(label, "dst").withColumn("many", F.count("*").over(Window.partitionBy("src", "label"))).where("many > 1")
    edges = materialise(met.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct())
    ids = edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct()
    few = edges.count() <= LOCAL_IDS // 2
    return TargetGraph(materialise(g.vertices.join(F.broadcast(ids) if few else ids, "id", "left_semi")), edges)


def kernel(g: TargetGraph, pattern: Pattern, alike: tuple[int, int] | None = None) -> TargetGraph:
    """g without edges that no occurrence can use, and without the vertices that then have none; every (not induced) occurrence is in it.

    alike: two pattern vertices whose images must have equal labels; used for wedges, whose every edge leads to one of its two ends.
    Labels and their neighbours' come first. Patterns without labels and with an edge on no triangle leave g as it is.
    """
    if alike and all(len({a, b} & set(alike)) == 1 for a, b in pattern.edges) and len(pattern.edges) == 2:
        g = _alike(g)
    if pattern.labels is not None:
        g = _labelled(g, pattern)
    least = support(pattern)
    if not least:
        return g
    t = materialise(triangles(g))
    if least > 1 and t.count() <= LOCAL_TRIANGLES:
        edges = materialise(t.withColumn("one", F.lit(0)).groupBy("one").applyInArrow(_peel(least), "src long, dst long"))
    else:
        edges = materialise(_sides(t).groupBy("src", "dst").agg(F.count("*").alias("n")).where(F.col("n") >= least).select("src", "dst"))
        left = edges.count()
        for _ in range(ROUNDS if least > 1 else 0):
            inside = _sides(t).join(edges, ["src", "dst"]).groupBy("x", "y", "z").count().where("count = 3")
            t = materialise(inside.select("x", "y", "z"))
            edges = materialise(_sides(t).groupBy("src", "dst").agg(F.count("*").alias("n")).where(F.col("n") >= least).select("src", "dst"))
            before, left = left, edges.count()
            if left == before:
                break
    ids = edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct()
    return TargetGraph(materialise(g.vertices.join(ids, "id", "left_semi")), edges)
