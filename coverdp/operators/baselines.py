"""Other methods for the same questions, and the bounds of those whose steps aren't given."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.model import TargetGraph
from coverdp.operators.clustering import uniform
from coverdp.operators.cover import ball_cover, single_bfs_cover
from coverdp.operators.dp_local import solve_pieces
from coverdp.patterns import Pattern
from coverdp.runtime import is_empty, materialise


def color_coding_decide(g: TargetGraph, pattern: Pattern, confidence: float = 1.0, seed: int = 1) -> DataFrame:
    """found, colourings: random colourings with k colours, occurrences of k different colours by joins with a mask of used ones."""
    k, n = pattern.k, g.vertices.count()
    most = math.ceil(math.e**k * confidence * math.log(max(n, 2)))
    arcs, done, batch, found = materialise(g.arcs), 0, 4, False
    while done < most and not found:
        batch = min(batch, most - done)
        c = g.vertices.select("id", F.explode(F.sequence(F.lit(done), F.lit(done + batch - 1))).alias("rep"))
        c = materialise(c.select("rep", "id", F.pow(F.lit(2), F.floor(uniform(seed, F.lit("cc"), "rep", "id") * k)).cast("int").alias("bit")))
        order = pattern.order
        df = c.select("rep", F.col("id").alias(f"v{order[0]}"), F.col("bit").alias("used"))
        for i, p in enumerate(order[1:], 1):
            near = [q for q in order[:i] if q in pattern.neighbours[p]]
            df = df.join(arcs.select(F.col("src").alias(f"v{near[0]}"), F.col("dst").alias(f"v{p}")), f"v{near[0]}")
            for q in near[1:]:
                df = df.join(arcs.select(F.col("src").alias(f"v{q}"), F.col("dst").alias(f"v{p}")), [f"v{q}", f"v{p}"], "left_semi")
            df = df.join(c.select("rep", F.col("id").alias(f"v{p}"), "bit"), ["rep", f"v{p}"]).where(F.col("used").bitwiseAND(F.col("bit")) == 0)
            df = df.withColumn("used", F.col("used").bitwiseOR(F.col("bit"))).drop("bit")
            # a vertex without further pattern neighbours needn't be kept: used colours keep the rest apart
            open_ = {f"v{q}" for q in order[: i + 1] if any(o in pattern.neighbours[q] for o in order[i + 1 :])}
            df = df.select("rep", "used", *sorted(open_)).distinct()
        found = bool(df.take(1))
        done += batch
        batch *= 2
    return g.spark.createDataFrame([(found, done)], "found boolean, colourings int")


def sequential_list(g: TargetGraph, pattern: Pattern, root: int) -> DataFrame:
    """mapping of every image: windows of one search from the root, no clustering, the program of each in turn; of the root's component."""
    from coverdp.operators.search import least_image

    _, pieces = single_bfs_cover(g, pattern.diameter, root)
    return solve_pieces(pieces, pattern, "list", images=True, engine="cells").select(least_image(F.col("mapping"), pattern).alias("mapping")).distinct()


def ball_list(g: TargetGraph, pattern: Pattern) -> DataFrame:
    """mapping of every image of a connected pattern: the ball around each vertex as a piece, each solved; exact, with quadratic total size at worst."""
    from coverdp.operators.search import least_image

    _, pieces = ball_cover(g, pattern.diameter)
    return solve_pieces(pieces, pattern, "list", images=True).select(least_image(F.col("mapping"), pattern).alias("mapping")).distinct()


def bounds_table(sizes: DataFrame, ks: tuple[int, ...] = (3, 4, 6)) -> DataFrame:
    """method, k, n, log2_work, log2_depth for graphs of sizes(n): the stated bounds with hidden constants 1."""
    grid = sizes.select(F.explode(F.array(*(F.lit(k) for k in ks))).alias("k"), "n").withColumns({"lk": F.log2(3 * F.col("k") + 1), "ln": F.log2("n"), "lln": F.log2(F.log2("n")), "kk": F.log2("k")})
    k, ln, lln = F.col("k"), F.col("ln"), F.col("lln")
    e = F.lit(math.log2(math.e))
    rows = {
        "color_splitting": (e * k + F.sqrt(k) * ln + lln, F.col("kk") + lln),
        "sequential_cover": (3 * k * F.col("lk") + ln, F.col("kk") + ln),
        "single_exponential": (18.81 * k + ln, 18.81 * k + ln),
        "sub_exponential": (k / F.greatest(F.col("kk"), F.lit(1.0)) + ln, k / F.greatest(F.col("kk"), F.lit(1.0)) + ln),
        "parallel_cover": (3 * k * F.col("lk") + ln + lln, F.col("kk") + 2 * lln),
    }
    out = None
    for name, (work, depth) in rows.items():
        one = grid.select(F.lit(name).alias("method"), "k", "n", F.round(work, 4).alias("log2_work"), F.round(depth, 4).alias("log2_depth"))
        out = one if out is None else out.union(one)
    return out


def windows_agree(a: DataFrame, b: DataFrame) -> bool:
    return is_empty(a.exceptAll(b)) and is_empty(b.exceptAll(a))
