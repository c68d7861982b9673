"""The program as reachability: paths of a decomposition layer by layer, each a graph of partial matches, with shortcuts."""

from __future__ import annotations

import math
from itertools import combinations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.operators.cover import PIECE
from coverdp.operators.dp_local import BELOW, UNMATCHED, Near, State, combine, introduce, lift
from coverdp.operators.paths import path_decomposition
from coverdp.operators.treedec import adjacency, eliminate
from coverdp.patterns import Pattern
from coverdp.runtime import is_empty, materialise

#: Ids of partial matches: piece number, node and rank of the state, in 63 bits.
NODE, RANK = 1 << 16, 1 << 20
MOST_PIECES = 1 << 27


def enumerate_matches(bag: list[int], pattern: Pattern, adj: dict[int, set[int]], below: bool = True) -> list[State]:
    """All partial matches of a bag: mapped parts keep adjacency, what lies below has no unmatched neighbour."""
    near, out = Near(adj), [(UNMATCHED,) * pattern.k]
    for v in bag:
        out += [t for s in list(out) for _, t in introduce(s, v, pattern, near, -1)]
    if below:
        more = []
        for s in out:
            free = [p for p in range(pattern.k) if s[p] == UNMATCHED]
            for r in range(1, len(free) + 1):
                for gone in combinations(free, r):
                    t = tuple(BELOW if p in gone else x for p, x in enumerate(s))
                    if all(t[q] != UNMATCHED for p in gone for q in pattern.neighbours[p]):
                        more.append(t)
        out += more
    return sorted(set(out))


class Window:
    """A piece's decomposition, its layers and paths."""

    def __init__(self, src: list[int], dst: list[int]) -> None:
        self.adj = adjacency(src, dst)
        self.order = eliminate(self.adj)
        n = len(self.order)
        if n > NODE:
            raise ValueError(f"a window of {n} vertices; ids of matches take {NODE} at most")
        self.kids: list[list[int]] = [[] for _ in range(n)]
        self.layer = [0] * n
        for i, (_, _, up) in enumerate(self.order):
            if self.kids[i]:
                best = max(self.layer[c] for c in self.kids[i])
                self.layer[i] = best + (sum(self.layer[c] == best for c in self.kids[i]) > 1)
            if up >= 0:
                self.kids[up].append(i)

    def bag(self, i: int) -> list[int]:
        v, near, _ = self.order[i]
        return sorted([v, *near])

    def before(self, i: int) -> int | None:
        """The child that goes on in the same path."""
        return next((c for c in self.kids[i] if self.layer[c] == self.layer[i]), None)


def _steps(w: Window, i: int, own: State | None, sides: list[list[State]], pattern: Pattern) -> set[State]:
    """Matches of node i that a match of its path child (None at a path's end) and valid matches of the other children combine to."""
    near, have = Near(w.adj), set()
    starts = {(UNMATCHED,) * pattern.k}
    parts = [([own], w.before(i))] if own is not None else []
    parts += list(zip(sides, [c for c in w.kids[i] if c != w.before(i)], strict=True))
    for states, c in parts:
        out_vertex, out_near, _ = w.order[c]
        lifted = {u for s in states if (u := lift(s, out_vertex, pattern)) is not None}
        shared = have & set(out_near)
        key = lambda s, shared=shared: tuple(x if x in shared else UNMATCHED for x in s)
        index: dict[State, list[State]] = {}
        for u in lifted:
            index.setdefault(key(u), []).append(u)
        starts = {b for s in starts for u in index.get(key(s), ()) if (b := combine(s, u, pattern, near)) is not None} if have else lifted
        have |= set(out_near)
    for v in w.bag(i):
        if v not in have:
            starts |= {t for s in starts for _, t in introduce(s, v, pattern, near, -1)}
    return starts


def match_dag(numbered: DataFrame, valid: DataFrame, pattern: Pattern, layer: int) -> DataFrame:
    """(piece_no, src, dst, adds_new): edges between partial matches along the paths of a layer; src null: a match valid by itself.

    numbered: piece edges with piece_no; valid: (piece_no, id) of valid matches of lower layers.
    """

    def run(edges: pa.Table, lower: pa.Table) -> pa.Table:
        rows = []
        if edges.num_rows:
            no = edges["piece_no"][0].as_py()
            w = Window(edges["src"].to_pylist(), edges["dst"].to_pylist())
            ids = set(lower["id"].to_pylist()) if lower.num_rows else set()
            every: dict[int, list[State]] = {}

            def states(i: int) -> list[State]:
                if i not in every:
                    every[i] = enumerate_matches(w.bag(i), pattern, w.adj)
                    if len(every[i]) > RANK:
                        raise ValueError(f"{len(every[i])} partial matches of a bag; ids of matches take {RANK} at most")
                return every[i]

            code = lambda i, s: (no * NODE + i) * RANK + states(i).index(s)
            for i in range(len(w.order)):
                if w.layer[i] != layer:
                    continue
                c = w.before(i)
                sides = [[s for r, s in enumerate(states(x)) if (no * NODE + x) * RANK + r in ids] for x in w.kids[i] if x != c]
                rank = {s: (no * NODE + i) * RANK + r for r, s in enumerate(states(i))}
                if c is None:
                    rows += [(no, None, rank[t], True) for t in _steps(w, i, None, sides, pattern) if t in rank]
                    continue
                for r, s in enumerate(states(c)):
                    free = sum(x == UNMATCHED for x in s)
                    rows += [(no, (no * NODE + c) * RANK + r, rank[t], free != sum(x == UNMATCHED for x in t)) for t in _steps(w, i, s, sides, pattern) if t in rank]
                rows += [(no, None, rank[s], True) for s in states(i) if BELOW not in s]
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 4
        return pa.table([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.bool_()), strict=True)], names=["piece_no", "src", "dst", "adds_new"])

    return numbered.groupBy("piece_no").cogroup(valid.groupBy("piece_no")).applyInArrow(run, "piece_no long, src long, dst long, adds_new boolean")


def lift_forest(dag: DataFrame) -> DataFrame:
    """node, parent: edges that match no new pattern vertex, of which each match has one at most."""
    return dag.where("src is not null and not adds_new").select(F.col("src").alias("node"), F.col("dst").alias("parent"))


def shortcuts(dag: DataFrame, mode: str) -> DataFrame:
    """src, dst, span. "all": from every match along its forest path by powers of two. "forest": the forest is split
    into paths, every L-th match of a path gets powers of two among these, and a jump to the head of the next path."""
    forest = lift_forest(dag)
    if mode == "none":
        return forest.select(F.col("node").alias("src"), F.col("parent").alias("dst"), F.lit(1).cast("long").alias("span")).limit(0)
    if mode == "all":
        span, step = 1, materialise(forest.select(F.col("node").alias("src"), F.col("parent").alias("dst")))
        out = step.withColumn("span", F.lit(1).cast("long"))
        while not is_empty(step):
            step = materialise(step.join(step.select(F.col("src").alias("dst"), F.col("dst").alias("far")), "dst").select("src", F.col("far").alias("dst")))
            span *= 2
            out = out.union(step.withColumn("span", F.lit(span).cast("long")))
        return materialise(out)
    roots = forest.select(F.col("parent").alias("node")).distinct().join(forest.select("node"), "node", "left_anti").select("node", F.lit(None).cast("long").alias("parent"))
    tree = materialise(forest.union(roots))
    paths = materialise(path_decomposition(tree))
    every = max(1, math.ceil(math.log2(max(2, tree.count()))))
    marked = paths.where(F.col("pos") % every == 0)
    # towards the top of the path positions fall
    step = materialise(marked.select("path", F.col("node").alias("src"), (F.col("pos") - every).alias("pos")).join(marked.select("path", "pos", F.col("node").alias("dst")), ["path", "pos"]).select("src", "dst"))
    span, out = every, step.withColumn("span", F.lit(every).cast("long"))
    while not is_empty(step):
        step = materialise(step.join(step.select(F.col("src").alias("dst"), F.col("dst").alias("far")), "dst").select("src", F.col("far").alias("dst")))
        span *= 2
        out = out.union(step.withColumn("span", F.lit(span).cast("long")))
    heads = tree.where("parent is not null").join(paths.where("pos = 0").select(F.col("path").alias("node")), "node").select("node", F.col("parent").alias("dst"))
    jumps = marked.select(F.col("node").alias("src"), F.col("path").alias("node")).join(heads, "node").select("src", "dst", F.lit(0).cast("long").alias("span"))
    return materialise(out.union(jumps))


def reach(dag: DataFrame, mode: str = "forest", counter: list | None = None) -> DataFrame:
    """id of every match that can be reached from one that is valid by itself. counter: gets the rounds."""
    jumps = shortcuts(dag, mode)
    edges = materialise(dag.where("src is not null").select("src", "dst").union(jumps.select("src", "dst")).distinct())
    seen = front = materialise(dag.where("src is null").select(F.col("dst").alias("id")).distinct())
    rounds = 0
    while not is_empty(front):
        front = materialise(front.select(F.col("id").alias("src")).join(edges, "src").select(F.col("dst").alias("id")).distinct().join(seen, "id", "left_anti"))
        seen = materialise(seen.union(front))
        rounds += 1
    if counter is not None:
        counter.append((mode, rounds, jumps.count()))
    return seen


def number_pieces(piece_edges: DataFrame) -> DataFrame:
    """piece_edges with piece_no, numbers from 0 without gaps: place within a partition, after the partitions before.

    The keys are written once, so that retried tasks see the same; only a count a partition goes to the driver.
    """
    spark = piece_edges.sparkSession
    keys = materialise(piece_edges.select(*PIECE).distinct().withColumn("raw", F.monotonically_increasing_id()))
    part = F.shiftright("raw", 33)
    first, begin = 0, []
    for r in keys.groupBy(part.alias("part")).count().orderBy("part").collect():
        begin.append((r["part"], first))
        first += r["count"]
    if first > MOST_PIECES:
        raise ValueError(f"{first} pieces; ids of matches take {MOST_PIECES} at a time")
    offsets = spark.createDataFrame(begin, "part long, begin long")
    numbered = keys.withColumn("part", part).join(F.broadcast(offsets), "part")  # a row a partition
    numbered = numbered.select(*PIECE, (F.col("begin") + F.col("raw").bitwiseAND((1 << 33) - 1)).alias("piece_no"))
    return piece_edges.select(*PIECE, "src", "dst").join(numbered, PIECE)


def solve_window_parallel(piece_edges: DataFrame, pattern: Pattern, mode: str = "forest", counter: list | None = None) -> DataFrame:
    """rep, center, start, piece_no, found of each piece: all paths of a layer of all pieces at once, a layer after the other."""
    numbered = materialise(number_pieces(piece_edges))

    def tops(t: pa.Table) -> pa.Table:
        w = Window(t["src"].to_pylist(), t["dst"].to_pylist())
        return pa.table({"top": pa.array([max(w.layer)], pa.int32())})

    top = numbered.groupBy("piece_no").applyInArrow(tops, "top int").agg(F.max("top")).collect()[0][0]
    spark = piece_edges.sparkSession
    valid = spark.createDataFrame([], "piece_no long, id long")
    for layer in range((top if top is not None else -1) + 1):
        dag = materialise(match_dag(numbered, valid, pattern, layer))
        got = reach(dag, mode, counter).select(F.shiftright("id", (NODE * RANK).bit_length() - 1).alias("piece_no"), "id")
        valid = materialise(valid.union(got))

    def accept(edges: pa.Table, ids: pa.Table) -> pa.Table:
        no = edges["piece_no"][0].as_py()
        w = Window(edges["src"].to_pylist(), edges["dst"].to_pylist())
        hit, known = False, {}
        for one in ids["id"].to_pylist():
            i, r = one // RANK % NODE, one % RANK
            if i not in known:
                known[i] = enumerate_matches(w.bag(i), pattern, w.adj)
            hit = hit or UNMATCHED not in known[i][r]
        return pa.table({"piece_no": pa.array([no], pa.int64()), "found": [hit]})

    found = numbered.groupBy("piece_no").cogroup(valid.groupBy("piece_no")).applyInArrow(accept, "piece_no long, found boolean")
    return numbered.select(*PIECE, "piece_no").distinct().join(found, "piece_no")
