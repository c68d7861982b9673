"""Patterns of several components, by random colourings."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.model import TargetGraph
from coverdp.operators.clustering import uniform
from coverdp.operators.search import PART_IDS, join_enumerate, least_image, list_occurrences, part_of
from coverdp.patterns import Pattern
from coverdp.runtime import materialise

#: Copies of a graph under different colourings lie side by side: the colouring's number above this bit of an id.
SHIFT = 52
#: Vertices of all copies that are searched at once; at least one copy is.
COPY_IDS = 8_000_000


def colourings(g: TargetGraph, colours: int, reps: int, seed: int, first: int = 0) -> TargetGraph:
    """`reps` copies of g, each vertex labelled by a random colour, with the edges of one colour."""
    rep = F.explode(F.sequence(F.lit(first), F.lit(first + reps - 1)))
    v = g.vertices.select("id", rep.alias("rep")).withColumn("colour", F.floor(uniform(seed, F.lit("colour"), "rep", "id") * colours).cast("int"))
    v = materialise(v.select("rep", "id", "colour"))
    new = lambda c: (F.shiftleft((F.col("rep") - first).cast("long"), SHIFT) + F.col(c))
    side = lambda c: v.select("rep", F.col("id").alias(c), F.col("colour").alias(f"{c}_colour"))
    e = g.edges.join(side("src"), "src").join(side("dst"), ["rep", "dst"]).where("src_colour = dst_colour")
    return TargetGraph(v.select(new("id").alias("id"), F.col("colour").cast("string").alias("label"), F.lit(None).cast("double").alias("x"), F.lit(None).cast("double").alias("y")), e.select(new("src").alias("src"), new("dst").alias("dst")))


def hit_rate(pattern: Pattern) -> float:
    """The chance that a colouring puts each component of one occurrence into its own colour."""
    return len(pattern.components) ** -float(pattern.k)


def colourings_needed(pattern: Pattern, n: int, confidence: float = 1.0) -> int:
    return math.ceil(confidence * math.log(max(n, 2)) / hit_rate(pattern))


def _by_component(g: TargetGraph, pattern: Pattern, reps: int, seed: int, solver: str, first: int):
    copies = colourings(g, len(pattern.components), reps, seed, first)
    copies = TargetGraph(materialise(copies.vertices), materialise(copies.edges))
    for i, own in enumerate(pattern.components):
        part = pattern.part(own)
        part = Pattern(part.k, part.edges, (str(i),) * part.k)
        got = join_enumerate(copies, part, images=False) if solver == "join" or part.k == 1 else list_occurrences(copies, part, images=False, seed=seed)
        low = F.transform("mapping", lambda x: x.bitwiseAND((1 << SHIFT) - 1))
        yield own, got.select(F.shiftright(F.get("mapping", F.lit(0)), SHIFT).alias("rep"), low.alias(f"m{i}"))


def decide_disconnected(g: TargetGraph, pattern: Pattern, confidence: float = 1.0, seed: int = 1, solver: str = "cover") -> DataFrame:
    """found, colourings: batches of colourings until one shows every component in its own colour, or there were enough. solver: "cover" or "join".

    A part of a large graph is searched first, by the same method: what it holds is an answer, and if it holds nothing the whole graph is searched.
    """
    n = g.vertices.count()
    if n > PART_IDS and (part := part_of(g, n)) is not None:
        got = decide_disconnected(part, pattern, confidence, seed, solver)
        if got.first()["found"]:
            return got
    most, done, batch = colourings_needed(pattern, n, confidence), 0, 2
    found = False
    while done < most and not found:
        batch = max(1, min(batch, most - done, COPY_IDS // max(1, n)))
        both = None
        for _, got in _by_component(g, pattern, batch, seed, solver, done):
            own = got.select("rep").distinct()
            both = own if both is None else both.join(own, "rep", "left_semi")
        found = bool(both.take(1))
        done += batch
        batch *= 2
    return g.spark.createDataFrame([(found, done)], "found boolean, colourings int")


def list_disconnected(g: TargetGraph, pattern: Pattern, reps: int | None = None, seed: int = 1, solver: str = "cover") -> DataFrame:
    """mapping (the least of each image) of every occurrence with high probability: the components' results joined by colouring."""
    n = g.vertices.count()
    reps = reps or 3 * colourings_needed(pattern, n)
    both, where = None, {}
    for i, (own, got) in enumerate(_by_component(g, pattern, reps, seed, solver, 0)):
        both = got if both is None else both.join(got, "rep")
        where |= {p: (i, j) for j, p in enumerate(own)}
    mapping = F.array(*(F.get(f"m{where[p][0]}", F.lit(where[p][1])) for p in range(pattern.k)))
    return both.select(least_image(mapping, pattern).alias("mapping")).distinct()


def split_exhaustive(g: TargetGraph, pattern: Pattern, most: int = 14) -> bool:
    """Baseline for tiny graphs: every split of the vertices into the colours."""
    from coverdp.operators.dp_local import solve
    from coverdp.operators.treedec import adjacency

    ids = sorted(r["id"] for r in g.vertices.select("id").limit(most + 1).collect())
    if len(ids) > most:
        raise ValueError(f"for {most} vertices at most")
    edges = [(r["src"], r["dst"]) for r in g.edges.collect()]
    parts = [pattern.part(own) for own in pattern.components]
    for split in range(len(parts) ** len(ids)):
        colour = {v: split // len(parts) ** i % len(parts) for i, v in enumerate(ids)}
        for c, part in enumerate(parts):
            own = [(a, b) for a, b in edges if colour[a] == colour[b] == c]
            if part.k == 1 and c in colour.values():
                continue
            if not own or not solve(adjacency(*zip(*own, strict=True)), part, None, "decide"):
                break
        else:
            return True
    return False
