"""Target graphs as two DataFrames."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Ids of vertices of kind j begin at j * KIND.
KIND = 1 << 48


@dataclass(frozen=True)
class TargetGraph:
    """vertices(id, label, x, y) and edges(src, dst) with src < dst, each edge once."""

    vertices: DataFrame
    edges: DataFrame

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    @property
    def arcs(self) -> DataFrame:
        """Each edge in both directions."""
        return self.edges.select("src", "dst").union(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))

    def degrees(self) -> DataFrame:
        return self.arcs.groupBy("src").agg(F.count("*").alias("degree")).select(F.col("src").alias("id"), "degree")

    def induced(self, members: DataFrame) -> TargetGraph:
        """The subgraph on members(id)."""
        ids = members.select("id").distinct()
        e = self.edges.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi")
        return TargetGraph(self.vertices.join(ids, "id", "left_semi"), e.select("src", "dst"))


def target_graph(vertices: DataFrame | None, edges: DataFrame) -> TargetGraph:
    """Put edges in canonical form (src < dst, no loops, no repeats) and fill in vertices that only edges name."""
    e = edges.select(F.least("src", "dst").cast("long").alias("src"), F.greatest("src", "dst").cast("long").alias("dst")).where("src <> dst").distinct()
    if vertices is None:
        vertices = e.select(F.col("src").alias("id")).union(e.select(F.col("dst").alias("id"))).distinct()
    have = set(vertices.columns)
    blank = {"label": "string", "x": "double", "y": "double"}
    return TargetGraph(vertices.select("id", *((F.col(c) if c in have else F.lit(None)).cast(t).alias(c) for c, t in blank.items())), e)
