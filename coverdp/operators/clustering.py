"""Random low-diameter clustering by exponential shifts, and what is built on it."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coverdp.model import TargetGraph
from coverdp.operators import blocks
from coverdp.runtime import is_empty, materialise

#: A step of distance, in the integer units of shifts.
UNIT = 1_000_000
#: Edges that one task holds; larger graphs are clustered by frontier joins.
LOCAL_EDGES = 4_000_000
HEX = 13


def uniform(seed: int, *keys: Column | str) -> Column:
    """A number in (0, 1) that depends on its keys alone: retried tasks and other engines draw the same."""
    text = F.concat_ws("|", F.lit(str(seed)), *(F.col(k).cast("string") if isinstance(k, str) else k.cast("string") for k in keys))
    return (F.conv(F.substring(F.md5(text), 1, HEX), 16, 10).cast("long") + 0.5) / float(16**HEX)


def draw_shifts(vertices: DataFrame, beta: float, reps: int, seed: int, first_rep: int = 0) -> DataFrame:
    """rep, id, shift: exponential with mean beta, in UNITs."""
    v = vertices.select("id").repartition(vertices.sparkSession.sparkContext.defaultParallelism, "id").withColumn("rep", F.explode(F.sequence(F.lit(first_rep), F.lit(first_rep + reps - 1))))
    return v.select("rep", "id", shift_of("rep", beta, seed).alias("shift"))


def shift_of(rep: Column | str, beta: float, seed: int) -> Column:
    return F.floor(-F.log(uniform(seed, rep, "id")) * (beta * UNIT)).cast("long")


def _bucketed(shift: Column) -> Column:
    """Rounded down to whole steps."""
    return (F.floor(shift / UNIT) * UNIT).cast("long")


def _neighbours(n: int, src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where each vertex's neighbours begin, and all of them."""
    return np.concatenate([[0], np.cumsum(np.bincount(src, minlength=n))]), dst[np.argsort(src, kind="stable")]


def _settle(begin: np.ndarray, near: np.ndarray, key: np.ndarray) -> np.ndarray:
    """Least key over paths, where a step costs one UNIT; keys hold a cost above 31 bits of a vertex number.

    Keys are settled in rising order, one UNIT's worth at a time: none of them can lower another, so each vertex sends once.
    """
    step = np.int64(UNIT) << 31
    key = key.copy()
    order = np.argsort(key)
    first = key[order]
    at, low, front = 0, first[0] if len(first) else 0, order[:0]
    while True:
        end = np.searchsorted(first, low + step)
        own = order[at:end][key[order[at:end]] == first[at:end]]
        at = end
        now = np.concatenate([own, front])
        low += step
        if not len(now):
            if at == len(first):
                return key
            low = first[at]
            continue
        many = begin[now + 1] - begin[now]
        into = near[np.repeat(begin[now] - np.cumsum(many) + many, many) + np.arange(many.sum())]
        offer = np.repeat(key[now] + step, many)
        better = offer < key[into]
        into = into[better]
        np.minimum.at(key, into, offer[better])
        front = np.unique(into)


def _near_cut(g: TargetGraph, cluster: DataFrame, steps: int) -> DataFrame:
    """cluster with near_cut: whether a vertex is within `steps` of an end of an edge that crosses clusters."""
    if "cut" in cluster.columns:  # ends are known already
        front, cluster = cluster.where("cut").select("rep", "id"), cluster.drop("cut")
    else:
        cluster = materialise(cluster)
        front = materialise(crossing_edges(g, cluster).where("crosses").select("rep", F.explode(F.array("src", "dst")).alias("id")).distinct())
    near = front
    for _ in range(steps):
        front = front.join(g.arcs.withColumnRenamed("src", "id"), "id").select("rep", F.col("dst").alias("id")).distinct()
        near = near.union(front)
    return cluster.join(near.distinct().withColumn("near", F.lit(True)), ["rep", "id"], "left").select(*cluster.columns, F.col("near").isNotNull().alias("near_cut"))


def _local(g: TargetGraph, shifts: DataFrame, steps: int | None = None) -> DataFrame:
    spark = g.spark
    # as arrays: rows of Python objects would take the driver over ten times the memory
    ids = np.sort(np.asarray(g.vertices.select("id").toArrow()["id"], dtype=np.int64))
    e = g.edges.select("src", "dst").toArrow()
    a, b = (np.searchsorted(ids, np.asarray(e[c], dtype=np.int64)).astype(np.int32) for c in ("src", "dst"))
    shared = spark.sparkContext.broadcast((ids, a, b))

    def run(table: pa.Table) -> pa.Table:
        ids, a, b = shared.value
        src, dst = np.concatenate([a, b]), np.concatenate([b, a])
        at = np.searchsorted(ids, np.asarray(table["id"]))
        s = np.zeros(len(ids), np.int64)
        s[at] = np.asarray(table["shift"])
        offset = int(s.max(initial=0))
        key = _settle(*_neighbours(len(ids), src, dst), ((offset - s) << 31) | np.arange(len(ids)))
        centre = key & ((1 << 31) - 1)
        level = ((key >> 31) - (offset - s[centre])) // UNIT
        rep = table["rep"][0].as_py() if len(table) else 0
        out = {"rep": pa.array(np.full(len(ids), rep), pa.int32()), "id": ids, "center": ids[centre], "level": level.astype(np.int32), "shift": s}
        if steps is not None:
            near = np.zeros(len(ids), bool)
            near[src[centre[src] != centre[dst]]] = True
            for _ in range(steps):
                near[dst[near[src]]] = True
            out["near_cut"] = near
        return pa.table(out)

    # partitions by number: small ones would be put together, and one task would cluster all repetitions
    spread = shifts.repartition(max(2, 4 * spark.sparkContext.defaultParallelism), "rep")
    return spread.groupBy("rep").applyInArrow(run, "rep int, id long, center long, level int, shift long" + (", near_cut boolean" if steps is not None else ""))


def _distributed(g: TargetGraph, shifts: DataFrame, most: int = 10_000) -> DataFrame:
    """Frontier rounds for all repetitions at once; only vertices that improved send on."""
    arcs = materialise(g.arcs)
    state = materialise(shifts.select("rep", "id", (-F.col("shift")).alias("cost"), F.col("id").alias("center")))
    front = state
    for _ in range(most):
        sent = front.join(arcs.withColumnRenamed("src", "id"), "id").groupBy("rep", F.col("dst").alias("id")).agg(F.min(F.struct((F.col("cost") + UNIT).alias("cost"), "center")).alias("offer"))
        both = state.join(sent, ["rep", "id"], "left").select("rep", "id", "cost", "center", "offer", (F.struct("cost", "center") > F.col("offer")).alias("better"))
        better = F.coalesce("better", F.lit(False))
        nxt = materialise(both.select("rep", "id", F.when(better, F.col("offer.cost")).otherwise(F.col("cost")).alias("cost"), F.when(better, F.col("offer.center")).otherwise(F.col("center")).alias("center"), better.alias("moved")))
        front = nxt.where("moved").drop("moved")
        state = nxt.drop("moved")
        if is_empty(front):
            break
    own = shifts.select("rep", F.col("id").alias("center"), "shift")
    out = state.join(own, ["rep", "center"]).withColumn("level", ((F.col("cost") + F.col("shift")) / UNIT).cast("int"))
    return out.select(F.col("rep").cast("int").alias("rep"), "id", "center", "level").join(shifts.select(F.col("rep").cast("int").alias("rep"), "id", "shift"), ["rep", "id"]).select("rep", "id", "center", "level", "shift")


def exponential_shift_clustering(g: TargetGraph, beta: float, reps: int, seed: int = 1, engine: str = "auto", mode: str = "exact", first_rep: int = 0, near_cut: int | None = None) -> DataFrame:
    """cluster(rep, id, center, level, shift): each vertex joins the centre of least distance minus shift, ties to the least id.

    level is the distance to the centre, which lies in the cluster. mode "bucketed": shifts are rounded down to whole
    steps, so that a vertex wakes in the round that its shift names. engine: "local" (a task a repetition, for graphs
    whose edges are counted first), "blocks" (ranges of ids as in coverdp.operators.blocks, where few vertices lie at their
    borders, else as "distributed"), "distributed" (frontier joins), or "auto"; all give the same rows. near_cut: a further
    column of that name, whether a vertex is within so many steps of an end of an edge between two clusters.
    """
    shifts = draw_shifts(g.vertices, beta, reps, seed, first_rep)
    if mode == "bucketed":
        shifts = shifts.withColumn("shift", _bucketed(F.col("shift")))
    if engine == "auto":
        engine = "local" if _fits(g) else "blocks"
    if engine == "local":
        return _local(g, shifts, near_cut)
    got = None
    if engine == "blocks":
        whole = _bucketed if mode == "bucketed" else lambda x: x
        got = blocks.settled(g, lambda r: whole(shift_of(F.lit(r), beta, seed)), beta, reps, first_rep, cut=near_cut is not None)
    if got is None:
        got = _distributed(g, shifts)
    return got if near_cut is None else _near_cut(g, got, near_cut)


def _fits(g: TargetGraph) -> bool:
    return g.edges.limit(LOCAL_EDGES + 1).count() <= LOCAL_EDGES


def crossing_counts(g: TargetGraph, beta: float, reps: int, seed: int = 1) -> tuple[int, int]:
    """Edges between clusters, and edges, over all repetitions; large graphs are counted block by block, without a table of clusters."""
    got = None if _fits(g) else blocks.settled(g, lambda r: shift_of(F.lit(r), beta, seed), beta, reps, counts=True)
    if got is not None:
        return tuple(got.agg(F.sum("crosses"), F.sum("edges")).first())
    cluster = materialise(exponential_shift_clustering(g, beta, reps, seed))
    return tuple(crossing_edges(g, cluster).agg(F.coalesce(F.sum(F.col("crosses").cast("long")), F.lit(0)), F.count("*")).first())


def cluster_levels(g: TargetGraph, cluster: DataFrame, root: str = "center", most: int = 10_000) -> DataFrame:
    """cluster with levels from its centre (as they are) or from its least id by a search of its own."""
    if root == "center":
        return cluster
    inner = edges_within(g, cluster).select("rep", "src", "dst")
    arcs = materialise(inner.union(inner.select("rep", F.col("dst").alias("src"), F.col("src").alias("dst"))))
    roots = cluster.groupBy("rep", "center").agg(F.min("id").alias("id"))
    seen = front = materialise(roots.select("rep", "id", F.lit(0).alias("lv")))
    for i in range(1, most):
        reached = front.join(arcs.withColumnRenamed("src", "id"), ["rep", "id"]).select("rep", F.col("dst").alias("id")).distinct()
        front = materialise(reached.join(seen, ["rep", "id"], "left_anti").select("rep", "id", F.lit(i).alias("lv")))
        if is_empty(front):
            break
        seen = seen.union(front)
    return cluster.join(seen, ["rep", "id"]).select("rep", "id", "center", F.col("lv").alias("level"), "shift")


def edges_within(g: TargetGraph, cluster: DataFrame, *carry: str) -> DataFrame:
    """rep, center, src, dst, src_level, dst_level of edges inside one cluster; carry: more columns of cluster, by end."""
    side = lambda end: cluster.select("rep", F.col("id").alias(end), F.col("center").alias(f"c_{end}"), F.col("level").alias(f"{end}_level"), *(F.col(c).alias(f"{end}_{c}") for c in carry))
    both = g.edges.join(side("src"), "src").join(side("dst"), ["rep", "dst"]).where("c_src = c_dst")
    return both.select("rep", F.col("c_src").alias("center"), "src", "dst", "src_level", "dst_level", *(f"{end}_{c}" for end in ("src", "dst") for c in carry))


def crossing_edges(g: TargetGraph, cluster: DataFrame) -> DataFrame:
    """rep, src, dst, crosses for every edge and repetition."""
    a = cluster.select("rep", F.col("id").alias("src"), F.col("center").alias("ca"))
    b = cluster.select("rep", F.col("id").alias("dst"), F.col("center").alias("cb"))
    return g.edges.join(a, "src").join(b, ["rep", "dst"]).select("rep", "src", "dst", (F.col("ca") != F.col("cb")).alias("crosses"))
