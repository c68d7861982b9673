"""Plane embeddings, their faces and the vertex-face graph."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coverdp.model import TargetGraph
from coverdp.runtime import is_empty, materialise

#: Faces are vertices of ids from here on in the vertex-face graph.
FACE = 1 << 58


def embedding_from_xy(g: TargetGraph) -> DataFrame:
    """darts(src, dst, nsrc, ndst): each arc with the one after it on the face to its left, from straight-line coordinates.

    One vertex may lie at infinity (x infinite): its edges leave the others away from the origin.
    """
    at = g.vertices.select("id", "x", "y")
    a = g.arcs.join(at.select(F.col("id").alias("src"), F.col("x").alias("sx"), F.col("y").alias("sy")), "src").join(at.select(F.col("id").alias("dst"), F.col("x").alias("dx"), F.col("y").alias("dy")), "dst")
    far = lambda c: F.coalesce(F.abs(F.col(c)) == float("inf"), F.lit(False))
    angle = F.when(far("dx"), F.atan2("sy", "sx")).when(far("sx"), -F.atan2("dy", "dx")).otherwise(F.atan2(F.col("dy") - F.col("sy"), F.col("dx") - F.col("sx")))
    w = W.partitionBy("src").orderBy(angle, "dst")
    everywhere = w.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    turn = a.select("src", "dst", F.coalesce(F.lag("dst").over(w), F.last("dst").over(everywhere)).alias("before"))
    # after u -> v comes v -> (the neighbour before u around v)
    return turn.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("src").alias("nsrc"), F.col("before").alias("ndst"))


def faces(darts: DataFrame) -> DataFrame:
    """src, dst, face for each dart; face: FACE plus a hash of the face's least dart, found by pointer doubling."""
    cur = materialise(darts.select("src", "dst", "nsrc", "ndst", F.struct("src", "dst").alias("m")))
    while True:
        ahead = cur.select(F.col("src").alias("nsrc"), F.col("dst").alias("ndst"), F.col("nsrc").alias("fsrc"), F.col("ndst").alias("fdst"), F.col("m").alias("fm"))
        nxt = materialise(cur.join(ahead, ["nsrc", "ndst"]).select("src", "dst", F.col("fsrc").alias("nsrc"), F.col("fdst").alias("ndst"), F.least("m", "fm").alias("m"), (F.col("fm") < F.col("m")).alias("moved")))
        moved = not is_empty(nxt.where("moved"))
        cur = nxt.drop("moved")
        if not moved:
            return cur.select("src", "dst", (F.xxhash64("m.src", "m.dst").bitwiseAND(FACE - 1) + FACE).alias("face"))


def vertex_face_graph(g: TargetGraph, face: DataFrame | None = None) -> TargetGraph:
    """The bipartite graph of vertices (label vertex) and faces (label face)."""
    face = faces(embedding_from_xy(g)) if face is None else face
    e = materialise(face.select("src", F.col("face").alias("dst")).distinct())
    v = g.vertices.select("id", F.lit("vertex").alias("label"), "x", "y").union(e.select("dst").distinct().select("dst", F.lit("face"), F.lit(None).cast("double"), F.lit(None).cast("double")))
    return TargetGraph(v, e)


def euler(g: TargetGraph) -> DataFrame:
    """n, m, f of a plane graph."""
    f = faces(embedding_from_xy(g)).select("face").distinct()
    return g.vertices.agg(F.count("*").alias("n")).crossJoin(g.edges.agg(F.count("*").alias("m"))).crossJoin(f.agg(F.count("*").alias("f")))  # one row each
