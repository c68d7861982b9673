"""Decide, find, list and count occurrences of a pattern."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from coverdp.model import TargetGraph
from coverdp.operators.clustering import exponential_shift_clustering
from coverdp.operators.cover import PIECE, window_edges
from coverdp.operators.dp_dist import solve_window_parallel
from coverdp.operators.dp_local import label_masks, solve_pieces
from coverdp.operators.kernel import kernel
from coverdp.patterns import Pattern, beta_for, repetitions
from coverdp.runtime import is_empty, materialise, release, scratch, tidy


FAMILIES = ("planar", "bounded_genus", "apex_minor_free")
ENGINES = ("batch", "layers")


def _span(pattern: Pattern) -> int:
    """The steps within which every vertex of the pattern has an end of any of its edges."""
    return max((min(pattern.distances[v][a], pattern.distances[v][b]) for a, b in pattern.edges for v in range(pattern.k)), default=0)


def _pieces(g: TargetGraph, pattern: Pattern, reps: int, seed: int, window: str, beta: float | None, first_rep: int, open_: DataFrame | None = None, turn_rows: int | None = None) -> tuple[list[DataFrame], bool, DataFrame]:
    """The windows of a batch of repetitions, whether they have masks, and the vertices that an occurrence unseen so far may use.

    turn_rows: the windows come in several tables, of the clusters that have about so many vertices together; else in one.

    Windows are cut down to vertices that some pattern vertex may be mapped to. A repetition shows every occurrence that no
    edge between two clusters cuts, so those that it shows first had such an edge in each earlier repetition, and all
    their vertices lie within _span of it: other vertices leave the windows. open_: the last result of earlier batches.
    """
    d = pattern.k - 1 if window == "safe" else pattern.diameter
    masks = pattern.labels is not None
    if masks:
        allowed = label_masks(g.vertices, pattern).where("mask > 0")
        g = g.induced(allowed)
    cluster = exponential_shift_clustering(g, beta or beta_for(pattern), reps, seed, first_rep=first_rep, near_cut=_span(pattern))
    if open_ is not None:
        cluster = cluster.join(open_, "id", "left_semi")
    far = F.min(F.when(~F.col("near_cut"), F.col("rep"))).over(Window.partitionBy("id"))  # the first repetition that shows all on this vertex
    cluster = cluster.withColumn("far", far).where("far is null or rep <= far").drop("far", "shift")
    if masks:
        cluster = cluster.join(allowed, "id")
    cluster = materialise(cluster)
    open_ = cluster.where((F.col("rep") == first_rep + reps - 1) & F.col("near_cut")).select("id")
    turns = 1 if turn_rows is None else max(1, -(-cluster.count() // turn_rows))
    own = [cluster.where(F.pmod(F.xxhash64("rep", "center"), F.lit(turns)) == i) if turns > 1 else cluster for i in range(turns)]
    return [window_edges(g, x, d, *(["mask"] if masks else [])) for x in own], masks, open_


def _accepted(pieces: DataFrame, pattern: Pattern, engine: str) -> DataFrame:
    """The pieces to expand. "batch": all; "layers": those that the layer-by-layer program with shortcuts accepts, so that only windows with an occurrence are walked again."""
    if engine not in ENGINES:
        raise ValueError(f"engine is one of {', '.join(ENGINES)}")
    if engine == "batch":
        return pieces
    if pattern.labels is not None:
        raise ValueError("the layers engine takes patterns without labels")
    pieces = materialise(pieces)
    return pieces.join(solve_window_parallel(pieces, pattern).where("found").select(*PIECE), PIECE, "left_semi")


def _size(g: TargetGraph) -> int:
    return g.vertices.count()


#: Vertices of a part that is searched before a larger graph: an occurrence in it is one of the graph.
PART_IDS = 100_000


def part_of(g: TargetGraph, n: int) -> TargetGraph | None:
    """The graph that the edges with the least lesser ends make, some PART_IDS of those; None if it isn't much smaller than g."""
    cut = g.edges.select(F.percentile_approx("src", PART_IDS / n, 10_000)).first()[0]
    if cut is None:
        return None
    edges = materialise(g.edges.where(F.col("src") <= cut))
    ids = edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
    vertices = materialise(g.vertices.join(ids, "id", "left_semi"))
    return None if 2 * vertices.count() > n else TargetGraph(vertices, edges)


def find(g: TargetGraph, pattern: Pattern, confidence: float = 1.0, seed: int = 1, window: str = "diameter", beta: float | None = None, engine: str = "batch") -> tuple[list[int] | None, int]:
    """(one mapping or None, repetitions used): batches of 1, 2, 4, ... repetitions until one holds an occurrence or absence is certain enough.

    Edges that lie on too few triangles for the pattern leave the graph first; if none is left, no repetition is needed.
    A part of a large graph is searched first, by the same method: what it holds is an answer, and if it holds nothing the whole graph is searched.

    engine: how windows are decided, "batch" (within tasks) or "layers" (partial matches as a graph, over all windows).
    """
    if not pattern.connected:
        raise ValueError("a disconnected pattern: see coverdp.operators.disconnected")
    n = _size(g)
    if n > PART_IDS and (part := part_of(g, n)) is not None:
        mapping, reps = find(part, pattern, confidence, seed, window, beta, engine)
        if mapping is not None:
            return mapping, reps
    most, done, batch = repetitions(n, confidence), 0, 1
    g = kernel(g, pattern)
    if is_empty(g.edges) and pattern.edges:
        return None, 0  # certainly absent
    unseen = None
    while done < most:
        batch = min(batch, most - done)
        (pieces,), masks, unseen = _pieces(g, pattern, batch, seed, window, beta, done, unseen)
        hit = solve_pieces(_accepted(pieces, pattern, engine), pattern, "find", masks=masks, images=True).orderBy("rep", "mapping").take(1)
        done += batch
        if hit:
            return hit[0]["mapping"], done
        batch *= 2
    return None, done


def decide(g: TargetGraph, pattern: Pattern, confidence: float = 1.0, seed: int = 1, window: str = "diameter", family: str = "planar", engine: str = "batch") -> DataFrame:
    """found, reps, n: whether the pattern occurs. A yes is certain; a no is wrong with probability n ** -confidence at most.

    family says what the windows' widths rest on. "planar": graphs with more edges than a planar one can have are refused
    (ValueError); "bounded_genus", "apex_minor_free": the same cover without that bound, as
    elimination decompositions don't need an embedding.
    """
    if family not in FAMILIES:
        raise ValueError(f"family is one of {', '.join(FAMILIES)}")
    if family == "planar" and (n := _size(g)) > 2 and g.edges.count() > 3 * n - 6:
        raise ValueError("too many edges for a planar graph; widths of windows aren't bounded by their levels")
    mapping, reps = find(g, pattern, confidence, seed, window, engine=engine)
    return g.spark.createDataFrame([(mapping is not None, reps, _size(g))], "found boolean, reps int, n long")


def should_stop(done: int, quiet: int, n: int, c: float = 1.0) -> bool:
    """After `done` repetitions, the last `quiet` of which brought nothing new."""
    return quiet >= math.log2(max(done, 1)) + c * math.log2(max(n, 2))


def _first_shown(got: DataFrame, known: DataFrame | None) -> DataFrame:
    """mapping, rep: of each occurrence that isn't known, the first repetition that shows it."""
    fresh = got.groupBy("mapping").agg(F.min("rep").alias("rep"))
    if known is None:
        return fresh
    fresh = materialise(fresh)
    if fresh.count() <= SENT_PAIRS:  # so that what is known needn't pass an exchange
        known = known.join(F.broadcast(fresh.select("mapping")), "mapping", "left_semi")
    return fresh.join(known.select("mapping"), "mapping", "left_anti")


#: Vertices of all repetitions of a batch, and of the windows that are solved at once: what listing has on disk beside its result follows these, not the graph's size times the repetitions.
BATCH_ROWS, TURN_ROWS = 10_000_000, 4_000_000


def list_occurrences(g: TargetGraph, pattern: Pattern, confidence: float = 1.0, seed: int = 1, window: str = "diameter", images: bool = True, batch: int | None = None, most: int = 4096, induced: bool = False, progress: list | None = None, engine: str = "batch", alike: tuple[int, int] | None = None) -> DataFrame:
    """mapping of every occurrence, each once, with high probability; images: one mapping of each class under automorphisms, its least.

    alike: two pattern vertices whose images must have equal labels; what can't meet that leaves the graph first, where the kernel knows how.

    Repetitions run in batches. Each batch gives, per occurrence, the first repetition that shows it; the stop rule is
    then evaluated repetition by repetition, so that its outcome doesn't depend on the batch size. Batches of large graphs are
    small, and what a batch wrote is deleted before the next.
    """
    if not pattern.connected:
        raise ValueError("a disconnected pattern: see coverdp.operators.disconnected")
    n = _size(g)
    if not induced:
        g = kernel(g, pattern, alike)
        if is_empty(g.edges) and pattern.edges:
            if progress is not None:
                progress.append(0)
            return g.spark.createDataFrame([], "mapping array<long>")
    batch = batch or math.ceil(confidence * math.log2(max(n, 2))) + 9  # mostly enough for the stop rule at once
    batch = max(1, min(batch, BATCH_ROWS // max(1, n)))
    known: DataFrame | None = None
    unseen: DataFrame | None = None
    done = quiet = 0
    while done < most:
        with scratch(g.spark) as keep:
            parts, masks, open_ = _pieces(g, pattern, batch, seed, window, None, done, unseen, TURN_ROWS)
            unseen, fresh = keep(materialise(open_)), []
            for pieces in parts:
                with scratch(g.spark) as keep_part:
                    got = solve_pieces(_accepted(pieces, pattern, engine), pattern, "list", masks=masks, induced=induced, images=images)
                    if images:
                        got = got.withColumn("mapping", least_image(F.col("mapping"), pattern))
                    fresh.append(keep_part(materialise(_first_shown(got, known))))
            # clusters of several repetitions may show an occurrence in two turns
            if batch > 1 and len(fresh) > 1:
                fresh = [materialise(reduce(DataFrame.union, fresh).groupBy("mapping").agg(F.min("rep").alias("rep")))]
            fresh = reduce(DataFrame.union, [keep(x) for x in fresh])
        news = {r["rep"]: r["count"] for r in fresh.groupBy("rep").count().collect()}
        stop_at = None
        for r in range(done, done + batch):
            quiet = 0 if news.get(r) else quiet + 1
            if should_stop(r + 1, quiet, n, confidence):
                stop_at = r
                break
        if stop_at is not None:
            fresh = fresh.where(F.col("rep") <= stop_at)
        known = fresh if known is None else known.union(fresh)
        done += batch
        if stop_at is not None:
            done = stop_at + 1
            break
    if progress is not None:
        progress.append(done)
    return known.select("mapping")


def least_image(mapping, pattern: Pattern):
    """The least of a mapping's rearrangements under the pattern's automorphisms: the same for all mappings of an image."""
    autos = pattern.automorphisms
    if len(autos) == math.factorial(pattern.k):
        return F.array_sort(mapping)
    return F.array_min(F.array(*(F.array(*(mapping[a[i]] for i in range(pattern.k))) for a in autos)))


def count_occurrences(g: TargetGraph, pattern: Pattern, **options) -> DataFrame:
    """images, mappings: the latter are the former times the automorphisms."""
    images = list_occurrences(g, pattern, images=True, **options)
    return images.agg(F.count("*").alias("images")).withColumn("mappings", F.col("images") * len(pattern.automorphisms))


#: Wedges that one exchange takes; more go in turns, so that disk doesn't follow their number.
TURN_WEDGES = 20_000_000
#: Pairs of ends that a join sends to every task.
SENT_PAIRS = 1_000_000


def _squares(g: TargetGraph) -> DataFrame:
    """mapping of every cycle of four vertices, each image once: two wedges over the same ends.

    Ids order the vertices, rising or falling, whichever makes fewer wedges. The first vertex z of a cycle is its highest, so a wedge
    z - x - w counts only where z is above x and w. Pairs of ends that only one wedge has are dropped before wedges are joined.
    """
    edges = materialise(g.edges.select("src", "dst"))
    pairs = F.col("count") * (F.col("count") - 1) / 2
    by_src, by_dst = (edges.groupBy(c).count().agg(F.coalesce(F.sum(pairs), F.lit(0.0)).alias("n")).first()["n"] for c in ("src", "dst"))
    sign = 1 if by_src <= by_dst else -1
    low, high = ("src", "dst") if sign > 0 else ("dst", "src")
    up = edges.select((F.col(low) * sign).alias("x"), (F.col(high) * sign).alias("z"))
    top, bottom = up.agg(F.max("x"), F.min("z")).first()
    above = materialise(up.groupBy("x").agg(F.collect_list("z").alias("ends")))
    release(edges)
    wedges = above.select("x", F.explode("ends").alias("z"), "ends").select("x", "z", F.explode("ends").alias("w")).where("w < z")
    many = min(by_src, by_dst)
    if top is not None and top >= bottom:  # else no vertex has one neighbour above it and one below
        flat = materialise(above.select("x", F.explode("ends").alias("z")))
        through = flat.select(F.col("z").alias("x"), F.col("x").alias("w")).join(flat, "x").select("x", "z", "w")
        many += through.count()
        wedges = wedges.union(through)
    turns = max(1, math.ceil(many / TURN_WEDGES))
    turn = F.pmod(F.xxhash64("z", "w"), F.lit(turns))
    found = None
    for i in range(turns):
        own = wedges.where(turn == i)
        ends = materialise(own.groupBy("z", "w").count().where("count > 1").select("z", "w"))
        tidy(ends)
        few = ends.count() <= SENT_PAIRS
        kept = materialise(own.join(F.broadcast(ends) if few else ends, ["z", "w"], "left_semi"))
        tidy(ends)
        both = kept.join(kept.withColumnRenamed("x", "y"), ["z", "w"]).where("x < y")
        found = both if found is None else found.union(both)
    return found.select(F.array(*(F.col(c) * sign for c in "zxwy")).alias("mapping"))


def join_enumerate(g: TargetGraph, pattern: Pattern, images: bool = True) -> DataFrame:
    """Baseline: every mapping by a chain of self-joins of the arcs, exact, without a cover. Images of 4-cycles without labels: by joining wedges with wedges."""
    if images and pattern.labels is None and pattern.k == 4 and len(pattern.edges) == 4 and all(len(x) == 2 for x in pattern.neighbours):
        a = next(iter(pattern.neighbours[0]))
        opposite = next(v for v in range(1, 4) if v not in pattern.neighbours[0])
        b = next(v for v in pattern.neighbours[0] if v != a)
        at = {0: 0, a: 1, opposite: 2, b: 3}
        return _squares(g).select(least_image(F.array(*(F.col("mapping")[at[p]] for p in range(4))), pattern).alias("mapping"))
    arcs = materialise(g.arcs)
    order = pattern.order
    labels = label_masks(g.vertices, pattern) if pattern.labels else None

    def fits(p: int, df: DataFrame, c: str) -> DataFrame:
        if labels is None or pattern.labels[p] is None:
            return df
        return df.join(labels.where(F.col("mask").bitwiseAND(1 << p) > 0).select(F.col("id").alias(c)), c, "left_semi")

    first = f"v{order[0]}"
    df = fits(order[0], g.vertices.select(F.col("id").alias(first)), first)
    seen = [order[0]]
    for p in order[1:]:
        c = f"v{p}"
        near = [q for q in seen if q in pattern.neighbours[p]]
        if near:
            df = df.join(arcs.select(F.col("src").alias(f"v{near[0]}"), F.col("dst").alias(c)), f"v{near[0]}")
            for q in near[1:]:
                df = df.join(arcs.select(F.col("src").alias(f"v{q}"), F.col("dst").alias(c)), [f"v{q}", c], "left_semi")
        else:
            df = df.crossJoin(g.vertices.select(F.col("id").alias(c)))  # a further component
        for q in seen:
            if q not in near:
                df = df.where(F.col(c) != F.col(f"v{q}"))
        df = fits(p, df, c)
        seen.append(p)
    mapping = F.array(*(F.col(f"v{p}") for p in range(pattern.k)))
    if images:
        return df.select(least_image(mapping, pattern).alias("mapping")).distinct()
    return df.select(mapping.alias("mapping"))
