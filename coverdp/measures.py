"""Cost and accuracy measures as rows (metric, value, bound, ok)."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coverdp.model import TargetGraph
from coverdp.operators.clustering import crossing_counts, crossing_edges, exponential_shift_clustering, uniform
from coverdp.operators.cover import PIECE, window_edges, windows
from coverdp.operators.dp_local import piece_measures
from coverdp.operators.search import join_enumerate, list_occurrences
from coverdp.operators.treedec import elimination_decomposition, violations, width
from coverdp.patterns import Pattern, beta_for
from coverdp.runtime import materialise

SCHEMA = "metric string, value double, bound double, ok boolean"


def _rows(spark: SparkSession, rows: list[tuple[str, float, float]], least: set[str] = frozenset()) -> DataFrame:
    return spark.createDataFrame([(m, float(v), float(b), bool(v >= b if m in least else v <= b)) for m, v, b in rows], SCHEMA)


def modelled_seconds(work: float, depth: float, executors: int) -> float:
    """Work shared by the executors, then the critical path."""
    return work / max(1, executors) + depth


def failure_probability(n: int, reps: int, survival: float = 0.5) -> float:
    return (1 - survival) ** reps


def _slack(p: float, size: int) -> float:
    return 3 * math.sqrt(p * (1 - p) / max(1, size / 50))  # neighbours fall together


def crossing_rate(g: TargetGraph, beta: float, reps: int = 8, seed: int = 1) -> DataFrame:
    """The first row of cluster_measures alone."""
    cross, pairs = crossing_counts(g, beta, reps, seed)
    return _rows(g.spark, [("crossing_rate", cross / max(1, pairs), 1 / beta + _slack(1 / beta, pairs))])


def cluster_measures(g: TargetGraph, pattern: Pattern, reps: int = 8, seed: int = 1, beta: float | None = None) -> DataFrame:
    """Crossing rate, radius and survival of occurrences, with three standard deviations of slack."""
    beta = beta or beta_for(pattern)
    cluster = materialise(exponential_shift_clustering(g, beta, reps, seed))
    n = g.vertices.count()
    cross, pairs = crossing_edges(g, cluster).agg(F.avg(F.col("crosses").cast("int")), F.count("*")).collect()[0]
    radius = cluster.agg(F.max("level")).collect()[0][0]
    x = materialise(join_enumerate(g, pattern).withColumn("occ", F.xxhash64("mapping")))
    who = x.select("occ", F.explode("mapping").alias("id")).join(cluster.select("rep", "id", "center"), "id").groupBy("rep", "occ").agg(F.count_distinct("center").alias("parts"))
    survive, seen = who.agg(F.avg((F.col("parts") == 1).cast("int")), F.count("*")).collect()[0]
    return _rows(
        g.spark,
        [("crossing_rate", cross or 0, 1 / beta + _slack(1 / beta, pairs)), ("cluster_radius", radius or 0, beta * (math.log(max(2, n * reps)) + 10)), ("survival_rate", survive if survive is not None else 1, 0.5 - _slack(0.5, seen))],
        {"survival_rate"},
    )


def cover_measures(g: TargetGraph, pattern: Pattern, reps: int = 2, seed: int = 1) -> DataFrame:
    """Multiplicity, total size, width, states and triples a node, and the checks of decompositions."""
    d, k = pattern.diameter, pattern.k
    cluster = materialise(exponential_shift_clustering(g, beta_for(pattern), reps, seed))
    v, e = windows(cluster, d), materialise(window_edges(g, cluster, d))
    n, m = g.vertices.count(), g.edges.count()
    most = v.groupBy("rep", "id").count().agg(F.max("count")).collect()[0][0]
    size = v.count() + e.count()
    p = piece_measures(e, pattern).agg(F.max("width"), F.max("states"), F.sum("triples"), F.sum("nodes")).collect()[0]
    tau = p[0] or 0
    bags = elimination_decomposition(e)
    return _rows(
        g.spark,
        [("window_multiplicity", most or 0, d + 1), ("cover_size", size, reps * (n + m) * (d + 1)), ("window_width", tau, 3 * d + 2), ("states_per_node", p[1] or 0, (tau + 3) ** k), ("triples_total", p[2] or 0, float(tau + 3) ** (3 * k) * max(1, p[3] or 1)), ("decomposition_nodes", p[3] or 0, 2 * max(1, e.count())), ("violations", violations(e, bags).count(), 0)],
    )


def listing_quality(g: TargetGraph, pattern: Pattern, seed: int = 1) -> DataFrame:
    """Recall and precision of the listing against the exact join, and its repetitions."""
    used: list[int] = []
    got = materialise(list_occurrences(g, pattern, seed=seed, progress=used))
    want = materialise(join_enumerate(g, pattern))
    x, y, both = want.count(), got.count(), got.join(want, "mapping", "left_semi").count()
    n = g.vertices.count()
    return _rows(g.spark, [("recall", both / max(1, x), 1.0), ("precision", both / max(1, y), 1.0), ("iterations", used[0], 8 * (math.log2(max(2, x)) + math.log2(max(2, n))))], {"recall", "precision"})


def coin_flip_tail(trials: DataFrame, flips: int = 64, seed: int = 1) -> DataFrame:
    """run, share, bound, ok, held: how many of trials(id) with `flips` tosses each hold a run of heads so long, against flips * 2 ** -run."""
    t = trials.withColumn("tosses", F.transform(F.sequence(F.lit(1), F.lit(flips)), lambda i: F.when(uniform(seed, F.col("id"), i) < 0.5, 1).otherwise(0)))
    start = F.struct(F.lit(0).alias("run"), F.lit(0).alias("best"))
    longest = F.aggregate("tosses", start, lambda a, x: F.struct(F.when(x == 1, a["run"] + 1).otherwise(0).alias("run"), F.greatest(a["best"], F.when(x == 1, a["run"] + 1).otherwise(0)).alias("best")), lambda a: a["best"])
    # one row a length of longest run; every asked length is there, held or not
    runs = materialise(t.groupBy(longest.alias("best")).agg(F.count("*").alias("n")))
    asked = runs.select("best", "n", F.explode(F.sequence(F.lit(4), F.lit(14))).alias("run"))
    out = asked.groupBy("run").agg(F.sum(F.when(F.col("best") >= F.col("run"), F.col("n")).otherwise(0)).alias("held"), F.sum("n").alias("all"))
    return out.withColumn("share", F.col("held") / F.col("all")).select("run", "held", "share", F.least(F.lit(1.0), flips * F.pow(F.lit(2.0), -F.col("run"))).alias("bound")).withColumn("ok", F.col("share") <= F.col("bound"))


def coloring_hits(g: TargetGraph, pattern: Pattern, reps: int = 64, seed: int = 1) -> DataFrame:
    """hits, total, near: mappings of a disconnected pattern, each under `reps` colourings; a hit has every component in its own colour.

    near: the share lies within five standard deviations of a reckoning that takes colourings, not mappings, as independent.
    """
    parts = len(pattern.components)
    own = {v: i for i, part in enumerate(pattern.components) for v in part}
    m = join_enumerate(g, pattern, images=False).withColumn("occ", F.monotonically_increasing_id())
    places = materialise(m.select("occ", F.posexplode("mapping").alias("place", "id")))
    colours = g.vertices.select("id", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))).alias("rep"))
    colours = colours.withColumn("colour", F.floor(uniform(seed, F.lit("colour"), "rep", "id") * parts).cast("int"))
    want = F.element_at(F.array(*(F.lit(own[v]) for v in range(pattern.k))), F.col("place") + 1)
    # a vertex of the wrong colour spoils the mapping; only right ones are counted together
    right = places.join(colours, "id").where(F.col("colour") == want).groupBy("occ", "rep").count().where(F.col("count") == pattern.k)
    total = places.select("occ").distinct().count() * reps
    rate = parts ** -float(pattern.k)
    slack = 5 * math.sqrt(rate / reps)
    return right.agg(F.count("*").alias("hits")).select("hits", F.lit(total).cast("long").alias("total"), (F.abs(F.col("hits") / F.lit(max(1, total)) - rate) <= slack).alias("near"))


def least_degree(g: TargetGraph) -> DataFrame:
    """least, planar_possible: the least degree, isolated vertices included; a planar graph has a vertex of degree five or less."""
    arcs = g.edges.select(F.col("src").alias("id")).union(g.edges.select(F.col("dst").alias("id")))
    degree = arcs.withColumn("one", F.lit(1)).union(g.vertices.select("id", F.lit(0))).groupBy("id").agg(F.sum("one").alias("degree"))
    return degree.agg(F.min("degree").alias("least")).withColumn("planar_possible", F.col("least") <= 5)


def recovered_cells(occurrences: DataFrame) -> DataFrame:
    """images, cells of listed occurrences(mapping): the size of an output, which any listing has to write."""
    return occurrences.agg(F.count("*").alias("images"), F.coalesce(F.sum(F.size("mapping")), F.lit(0)).cast("long").alias("cells"))


def check_target(g: TargetGraph) -> DataFrame:
    """n, m, planar_possible: whether the edge count allows a planar graph."""
    n = g.vertices.agg(F.count("*").alias("n"))
    m = g.edges.agg(F.count("*").alias("m"))
    return n.crossJoin(m).withColumn("planar_possible", (F.col("n") < 3) | (F.col("m") <= 3 * F.col("n") - 6))  # one row each


def window_widths(g: TargetGraph, pattern: Pattern, seed: int = 1) -> DataFrame:
    """rep, center, start, width of each window: the probe of local treewidth."""
    cluster = materialise(exponential_shift_clustering(g, beta_for(pattern), 1, seed))
    return width(elimination_decomposition(window_edges(g, cluster, pattern.diameter))).select(*PIECE, "width")
