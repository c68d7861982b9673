"""Overlapping windows of levels, in which every occurrence of small diameter that a cluster keeps lies whole."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.model import TargetGraph
from coverdp.operators.clustering import edges_within, exponential_shift_clustering
from coverdp.patterns import Pattern, beta_for
from coverdp.runtime import is_empty, materialise

PIECE = ["rep", "center", "start"]


def windows(cluster: DataFrame, d: int) -> DataFrame:
    """piece_vertices(rep, center, start, id, level): levels start..start+d; windows after the last full one are dropped."""
    top = cluster.groupBy("rep", "center").agg(F.max("level").alias("top"))
    last = F.greatest(F.lit(0), F.col("top") - d)
    v = cluster.join(top, ["rep", "center"])
    spans = F.sequence(F.least(F.greatest(F.lit(0), F.col("level") - d), last), F.least(F.col("level"), last))
    return v.select("rep", "center", F.explode(spans).alias("start"), "id", "level")


def window_edges(g: TargetGraph, cluster: DataFrame, d: int, *carry: str) -> DataFrame:
    """piece_edges(rep, center, start, src, dst, src_level, dst_level, last): edges with both ends in a window."""
    top = cluster.groupBy("rep", "center").agg(F.max("level").alias("top"))
    e = edges_within(g, cluster, *carry).join(top, ["rep", "center"]).withColumn("last", F.greatest(F.lit(0), F.col("top") - d))
    lo = F.least(F.greatest(F.lit(0), F.greatest("src_level", "dst_level") - d), F.col("last"))
    spans = F.sequence(lo, F.least("src_level", "dst_level", "last"))
    e = e.where(lo <= F.least("src_level", "dst_level", "last"))
    return e.select("rep", "center", F.explode(spans).alias("start"), "src", "dst", "src_level", "dst_level", "last", *(f"{end}_{c}" for end in ("src", "dst") for c in carry))


def treewidth_cover(g: TargetGraph, pattern: Pattern, reps: int = 1, seed: int = 1, window: int | None = None, beta: float | None = None) -> tuple[DataFrame, DataFrame]:
    """(piece_vertices, piece_edges). window: levels beyond the first; the pattern's diameter unless given (k - 1 is safe for an unknown one)."""
    cluster = materialise(exponential_shift_clustering(g, beta or beta_for(pattern), reps, seed))
    d = pattern.diameter if window is None else window
    return windows(cluster, d), window_edges(g, cluster, d)


def prune_pieces(pieces: DataFrame, pattern: Pattern) -> DataFrame:
    """piece_edges without the pieces of fewer vertices or edges than the pattern."""
    size = pieces.groupBy(*PIECE).agg(F.count("*").alias("m"))
    ends = pieces.select(*PIECE, F.explode(F.array("src", "dst")).alias("id")).groupBy(*PIECE).agg(F.count_distinct("id").alias("n"))
    keep = size.join(ends, PIECE).where((F.col("m") >= len(pattern.edges)) & (F.col("n") >= pattern.k))
    return pieces.join(keep.select(*PIECE), PIECE, "left_semi")


def bfs_levels(g: TargetGraph, root: int, most: int = 100_000) -> DataFrame:
    """id, level from root; vertices out of reach are absent."""
    arcs = materialise(g.arcs)
    seen = front = materialise(g.vertices.where(F.col("id") == root).select("id", F.lit(0).alias("level")))
    for i in range(1, most):
        reached = front.join(arcs.withColumnRenamed("src", "id"), "id").select(F.col("dst").alias("id")).distinct()
        front = materialise(reached.join(seen, "id", "left_anti").select("id", F.lit(i).alias("level")))
        if is_empty(front):
            break
        seen = seen.union(front)
    return seen


def single_bfs_cover(g: TargetGraph, d: int, root: int) -> tuple[DataFrame, DataFrame]:
    """Windows of one breadth-first search without clusters: its depth is the graph's diameter."""
    cluster = materialise(bfs_levels(g, root).select(F.lit(0).alias("rep"), "id", F.lit(root).cast("long").alias("center"), "level"))
    return windows(cluster, d), window_edges(g, cluster, d)


def ball_cover(g: TargetGraph, d: int) -> tuple[DataFrame, DataFrame]:
    """The d-hop ball of every vertex as a piece: total size may be quadratic."""
    arcs = g.arcs
    ball = g.vertices.select(F.col("id").alias("center"), "id", F.lit(0).alias("level"))
    front = ball
    for i in range(1, d + 1):
        front = front.join(arcs.withColumnRenamed("src", "id"), "id").select("center", F.col("dst").alias("id"), F.lit(i).alias("level"))
        ball = ball.union(front)
    ball = ball.groupBy("center", "id").agg(F.min("level").alias("level"))
    v = ball.select(F.lit(0).alias("rep"), "center", F.lit(0).alias("start"), "id", "level")
    a = v.select("rep", "center", "start", F.col("id").alias("src"), F.col("level").alias("src_level"))
    b = v.select("center", F.col("id").alias("dst"), F.col("level").alias("dst_level"))
    e = g.edges.join(a, "src").join(b, ["center", "dst"])
    return v, e.select("rep", "center", "start", "src", "dst", "src_level", "dst_level", F.lit(0).alias("last"))
