"""Components, contraction, separating patterns and the vertex connectivity of plane graphs."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.model import TargetGraph, target_graph
from coverdp.operators.clustering import exponential_shift_clustering
from coverdp.operators.cover import PIECE, windows
from coverdp.operators.embedding import embedding_from_xy, faces, vertex_face_graph
from coverdp.operators.search import join_enumerate
from coverdp.operators.treedec import adjacency, eliminate
from coverdp.patterns import Pattern, beta_for, cycle, repetitions
from coverdp.runtime import is_empty, materialise

#: Edges of a graph that every task gets whole, to test candidates against.
MOST_EDGES = 2_000_000


def connected_components(g: TargetGraph, most: int = 200) -> DataFrame:
    """id, component (the least id) by alternating star contraction; isolated vertices stand alone."""
    e = materialise(g.edges.select(F.col("dst").alias("hi"), F.col("src").alias("lo")))
    for _ in range(most):
        both = e.union(e.select(F.col("lo").alias("hi"), F.col("hi").alias("lo")))
        least = both.groupBy("hi").agg(F.min("lo").alias("m")).select("hi", F.least("hi", "m").alias("m"))
        large = both.where("lo > hi").join(least, "hi").where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo")).distinct()
        root = large.groupBy("hi").agg(F.min("lo").alias("m"))
        hooked = large.join(root, "hi").where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo")).union(root.select("hi", F.col("m").alias("lo")))
        e = materialise(hooked.select(F.greatest("hi", "lo").alias("hi"), F.least("hi", "lo").alias("lo")).where("hi <> lo").distinct())
        if is_empty(e.join(e.select(F.col("hi").alias("lo")), "lo", "left_semi")) and is_empty(e.groupBy("hi").count().where("count > 1")):
            break
    return g.vertices.select("id").join(e.select(F.col("hi").alias("id"), "lo"), "id", "left").select("id", F.coalesce("lo", "id").alias("component"))


def contract(g: TargetGraph, relabel: DataFrame) -> TargetGraph:
    """The minor where every id of relabel(id, to) becomes `to`; other vertices stay, loops and repeats go."""
    r = relabel.select("id", "to")
    e = g.edges.join(r.select(F.col("id").alias("src"), F.col("to").alias("ts")), "src", "left").join(r.select(F.col("id").alias("dst"), F.col("to").alias("td")), "dst", "left")
    e = e.select(F.coalesce("ts", "src").alias("src"), F.coalesce("td", "dst").alias("dst"))
    v = g.vertices.select("id").join(r, "id", "left").select(F.coalesce("to", "id").alias("id")).distinct()
    return target_graph(v, e)


def cut_vertices(g: TargetGraph, face: DataFrame | None = None) -> DataFrame:
    """id of every cut vertex of a plane graph: it is met twice on the walk around one face."""
    face = faces(embedding_from_xy(g)) if face is None else face
    return face.groupBy("face", "src").count().where("count > 1").select(F.col("src").alias("id")).distinct()


def forest_cut_vertices(g: TargetGraph) -> DataFrame:
    """id of every cut vertex of a forest: those with two neighbours or more."""
    return g.degrees().where("degree > 1").select("id")


def separates(adj: dict[int, set[int]], removed: set[int], marked: set[int]) -> bool:
    """Whether marked vertices lie in two components at least once `removed` is gone."""
    left = [v for v in marked if v not in removed and v in adj]
    if not left:
        return False
    seen, stack = {left[0]}, [left[0]]
    while stack:
        for w in adj[stack.pop()]:
            if w not in removed and w not in seen:
                seen.add(w)
                stack.append(w)
    return any(v not in seen for v in left)


class Separation:
    """The test of `separates` for many small sets of one graph: searches from the neighbours of a set, side by side, that end once all but one met or ran out."""

    def __init__(self, adj: dict[int, set[int]], marked: set[int]) -> None:
        self.adj, self.marked = adj, marked
        self.part: dict[int, int] = {}
        self.many: list[int] = []  # marked vertices of each component of the whole graph
        for v in adj:
            if v in self.part:
                continue
            at = len(self.many)
            self.part[v], stack, n = at, [v], 0
            while stack:
                x = stack.pop()
                n += x in marked
                for w in adj[x]:
                    if w not in self.part:
                        self.part[w] = at
                        stack.append(w)
            self.many.append(n)
        self.held = sum(n > 0 for n in self.many)

    def test(self, removed: set[int]) -> bool:
        gone: dict[int, int] = {}
        for v in removed:
            if v in self.part:
                gone.setdefault(self.part[v], 0)
                gone[self.part[v]] += v in self.marked
        # components of the whole graph that still hold marked vertices
        held = self.held - sum(self.many[c] > 0 for c in gone) + sum(self.many[c] > n for c, n in gone.items())
        if held != 1:
            return held > 1
        return any(self.many[c] > n and self._parts(removed, c, self.many[c] - n) for c, n in gone.items())

    def _parts(self, removed: set[int], component: int, left: int) -> bool:
        """Whether the `left` marked vertices of a component lie in two pieces at least without `removed`."""
        starts = sorted({w for v in removed if self.part.get(v) == component for w in self.adj[v]} - removed)
        owner = {v: i for i, v in enumerate(starts)}
        up = list(range(len(starts)))
        front = [[v] for v in starts]
        found = [int(v in self.marked) for v in starts]

        def top(i: int) -> int:
            while up[i] != i:
                up[i] = up[up[i]]
                i = up[i]
            return i

        live = set(up)
        while len(live) > 1:
            for i in list(live):
                if i not in live:
                    continue
                if not front[i]:  # a whole piece
                    if 0 < found[i] < left:
                        return True
                    if found[i] == left:
                        return False
                    live.discard(i)
                    continue
                step, front[i] = front[i], []
                for v in step:
                    for w in self.adj[v]:
                        if w in removed:
                            continue
                        i = top(i)
                        if w not in owner:
                            owner[w] = i
                            front[i].append(w)
                            found[i] += w in self.marked
                        elif (j := top(owner[w])) != i:
                            live.discard(j)
                            up[j] = i
                            front[i] += front[j]
                            found[i] += found[j]
                            front[j] = []
        return False


def separating_occurrence(adj: dict[int, set[int]], pattern: Pattern, allowed: dict[int, int], marked: set[int], counters: dict | None = None) -> bool:
    """Whether some occurrence separates the marked vertices of a piece: the program with an inside and an outside.

    A bag vertex is mapped to a pattern vertex, inside or outside; no edge joins inside and outside; two flags tell
    whether a marked vertex was seen on either side. Both must be set at the root, with nothing unmatched.
    """
    k, full = pattern.k, (1 << pattern.k) - 1
    near = [sum(1 << q for q in nb) for nb in pattern.neighbours]
    in_, out_ = k, k + 1
    order = eliminate(adj)
    kids: list[list[int]] = [[] for _ in order]
    for i, (_, _, up) in enumerate(order):
        if up >= 0:
            kids[up].append(i)
    # a state: what each bag vertex is, in the order of the bag; pattern vertices below; flags inside 1, outside 2
    tables: list[set] = [set() for _ in order]
    roots = []
    peak = 0

    def fits(assign: dict[int, int], x: int, role: int, below: int) -> bool:
        if role < k:
            if not allowed.get(x, 0) >> role & 1 or below >> role & 1 or below & near[role]:
                return False
            for y, r in assign.items():
                if r == role or r < k and near[role] >> r & 1 and y not in adj[x]:
                    return False
            return True
        return all(r == role or r < k or y not in adj[x] for y, r in assign.items())

    for i, (v, nb, up) in enumerate(order):
        cur: list[tuple[tuple[int, ...], int, int]] = [((), 0, 0)]
        known: list[int] = []
        for c in kids[i]:
            cv, cnb, _ = order[c]
            lifted = set()
            for assign, below, flags in tables[c]:
                role = assign[0]
                rest = assign[1:]
                if role < k:
                    have = below | sum(1 << r for r in rest if r < k) | 1 << role
                    if near[role] & ~have:
                        continue
                    below |= 1 << role
                lifted.add((rest, below, flags))
            tables[c] = set()
            shared = [x for x in cnb if x in known]
            fresh = [x for x in cnb if x not in known]
            index: dict[tuple, list] = {}
            for rest, below, flags in lifted:
                a = dict(zip(cnb, rest, strict=True))
                index.setdefault(tuple(a[x] for x in shared), []).append((tuple(a[x] for x in fresh), below, flags))
            nxt = set()
            for assign, below, flags in cur:
                a = dict(zip(known, assign, strict=True))
                used = below | sum(1 << r for r in assign if r < k)
                for extra, b2, f2 in index.get(tuple(a[x] for x in shared), ()):
                    if b2 & used or below & sum(1 << r for r in extra if r < k):
                        continue
                    d = dict(a)
                    for x, r in zip(fresh, extra, strict=True):
                        if not fits(d, x, r, 0):
                            break
                        d[x] = r
                    else:
                        nxt.add((assign + extra, below | b2, flags | f2))
            cur, known = list(nxt), known + fresh
        bag = [v, *nb]
        for x in bag:
            if x in known:
                continue
            nxt = set()
            for assign, below, flags in cur:
                a = dict(zip(known, assign, strict=True))
                for role in range(k + 2):
                    if fits(a, x, role, below):
                        nxt.add((assign + (role,), below, flags | ((1 if role == in_ else 2) if role >= k and x in marked else 0)))
            cur, known = list(nxt), [*known, x]
        at = [known.index(x) for x in bag]
        table = set()
        for assign, below, flags in cur:
            table.add((tuple(assign[j] for j in at), below, flags))
        peak = max(peak, len(table))
        if up < 0:
            done = set()
            for assign, below, flags in table:
                if below | sum(1 << r for r in assign if r < k) == full:
                    done.add((full, flags))
                elif not below and all(r >= k for r in assign):
                    done.add((0, flags))
            roots.append(done)
        else:
            tables[i] = table
    if counters is not None:
        counters["states"] = max(counters.get("states", 0), peak)
    # several components: one holds the occurrence, the others lie on one side each
    total = {(0, 0)}
    for done in roots:
        total = {(m | m2, f | f2) for m, f in total for m2, f2 in done if not m & m2}
    return (full, 3) in total


def separating_cover(g: TargetGraph, pattern: Pattern, marked: DataFrame, reps: int = 1, seed: int = 1, contract_rest: bool = True) -> DataFrame:
    """rep, center, start, src, dst, src_allowed, dst_allowed, src_marked, dst_marked: windows with what lies outside contracted.

    The components of the graph without the window become one vertex each: unmappable, marked if any of theirs is.
    contract_rest=False leaves them out, which gives wrong answers; it is kept to show that. The graph's edges go to
    every task, up to MOST_EDGES of them.
    """
    cluster = materialise(exponential_shift_clustering(g, beta_for(pattern), reps, seed))
    if g.edges.limit(MOST_EDGES + 1).count() > MOST_EDGES:
        raise ValueError("too many edges to contract within a task; crop or decompose by connected component first")
    shared = g.spark.sparkContext.broadcast((g.edges.toPandas().to_numpy(np.int64), {r["id"] for r in marked.select("id").toLocalIterator()}))

    def run(t: pa.Table) -> pa.Table:
        edges, mark = shared.value
        adj = adjacency(edges[:, 0].tolist(), edges[:, 1].tolist())
        window = set(t["id"].to_pylist())
        name = {v: v for v in window}
        marks = {v: v in mark for v in window}
        if contract_rest:
            for s in adj:
                if s in name:
                    continue
                name[s], stack, hit = -1 - s, [s], s in mark
                while stack:
                    for w in adj[stack.pop()]:
                        if w not in name:
                            name[w] = -1 - s
                            hit |= w in mark
                            stack.append(w)
                marks[-1 - s] = hit
        rows = {(min(a, b), max(a, b)) for x, y in edges.tolist() if x in name and y in name and (a := name[x]) != (b := name[y])}
        head = [t[c][0].as_py() for c in PIECE]
        cols = list(zip(*[(*head, a, b, a >= 0, b >= 0, marks[a], marks[b]) for a, b in sorted(rows)], strict=True)) or [[]] * 9
        kinds = (pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), *(pa.bool_(),) * 4)
        return pa.table([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=[*PIECE, "src", "dst", "src_allowed", "dst_allowed", "src_marked", "dst_marked"])

    return windows(cluster, pattern.diameter).groupBy(*PIECE).applyInArrow(run, "rep int, center long, start int, src long, dst long, src_allowed boolean, dst_allowed boolean, src_marked boolean, dst_marked boolean")


def decide_separating(g: TargetGraph, pattern: Pattern, marked: DataFrame, reps: int | None = None, seed: int = 1, contract_rest: bool = True, sides: tuple[str, ...] | None = None) -> bool:
    """Whether some occurrence's removal leaves marked vertices in two components. sides: labels of the pattern's vertices.

    reps: None for as many as make a wrong no as likely as 1 / n at most.
    """
    reps = repetitions(g.vertices.count()) if reps is None else reps
    pieces = separating_cover(g, pattern, marked, reps, seed, contract_rest)
    full = (1 << pattern.k) - 1
    label = {} if sides is None else {r["id"]: r["label"] for r in g.vertices.select("id", "label").toLocalIterator()}
    masks = None if sides is None else {x: sum(1 << p for p, s in enumerate(sides) if s == x) for x in set(sides)}

    def run(t: pa.Table) -> pa.Table:
        src, dst = t["src"].to_pylist(), t["dst"].to_pylist()
        ok = dict(zip(src + dst, t["src_allowed"].to_pylist() + t["dst_allowed"].to_pylist(), strict=True))
        marks = {v for v, m in zip(src + dst, t["src_marked"].to_pylist() + t["dst_marked"].to_pylist(), strict=True) if m}
        allowed = {v: (full if masks is None else masks.get(label[v], 0)) if x else 0 for v, x in ok.items()}
        return pa.table({"found": [separating_occurrence(adjacency(src, dst), pattern, allowed, marks)]})

    return bool(pieces.groupBy(*PIECE).applyInArrow(run, "found boolean").where("found").take(1))


def decide_separating_cycle(g: TargetGraph, length: int, marked: DataFrame, **options) -> bool:
    """Whether some cycle of `length` vertices separates the marked ones; options as of decide_separating."""
    return decide_separating(g, cycle(length), marked, **options)


def enumerate_then_separate(g: TargetGraph, pattern: Pattern, marked: DataFrame, labels: tuple[str, ...] | None = None) -> DataFrame:
    """Baseline: mapping of every occurrence whose removal separates the marked vertices; each is tested on its own."""
    if g.edges.limit(MOST_EDGES + 1).count() > MOST_EDGES:
        raise ValueError("too many edges to test candidates against within a task")
    p = Pattern(pattern.k, pattern.edges, labels) if labels else pattern
    shared = g.spark.sparkContext.broadcast((g.edges.toPandas().to_numpy(np.int64), {r["id"] for r in marked.select("id").toLocalIterator()}))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        edges, mark = shared.value
        parted = Separation(adjacency(edges[:, 0].tolist(), edges[:, 1].tolist()), mark)
        for b in batches:
            yield b.filter(pa.array([parted.test(set(m)) for m in b.column(0).to_pylist()], pa.bool_()))

    return join_enumerate(g, p).mapInArrow(run, "mapping array<long>")


def vertex_connectivity(g: TargetGraph, method: str = "auto", seed: int = 1) -> int:
    """0 to 5, of a plane graph with coordinates (or a forest without).

    Shared steps: components, complete graphs, cut vertices, then the shortest separating cycle of length 4, 6 or 8 of
    the vertex-face graph, none meaning 5; the least degree bounds the search. method "program": windows with an inside
    and an outside; "enumerate": all cycles, each tested; "auto": the program for short cycles of small graphs.
    """
    n, m = g.vertices.count(), g.edges.count()
    if m == n * (n - 1) // 2:
        return max(0, n - 1)
    if connected_components(g).select("component").distinct().limit(2).count() > 1:
        return 0
    least = g.degrees().agg(F.min("degree")).collect()[0][0]
    if least == 1 or m == n - 1:
        return 1
    face = materialise(faces(embedding_from_xy(g)))
    if not is_empty(cut_vertices(g, face)):
        return 1
    vf = vertex_face_graph(g, face)
    vf = TargetGraph(materialise(vf.vertices), vf.edges)
    marked = vf.vertices.where("label = 'vertex'")
    for c in (2, 3, 4):
        if c == least:
            return c
        sides = ("vertex", "face") * c
        by_program = method == "program" or method == "auto" and c == 2 and n <= 200
        if decide_separating(vf, cycle(2 * c), marked, None, seed, True, sides) if by_program else bool(enumerate_then_separate(vf, cycle(2 * c), marked, sides).take(1)):
            return c
    return 5


def is_c_connected(g: TargetGraph, c: int) -> bool:
    return vertex_connectivity(g) >= c


def is_connected(g: TargetGraph) -> bool:
    return connected_components(g).select("component").distinct().limit(2).count() <= 1


def is_biconnected(g: TargetGraph, face: DataFrame | None = None) -> bool:
    """Whether a plane graph of three vertices or more is connected and has no cut vertex."""
    return g.vertices.limit(3).count() == 3 and is_connected(g) and is_empty(cut_vertices(g, face))


def is_triconnected(g: TargetGraph, seed: int = 1) -> bool:
    """Whether a plane graph of four vertices or more stays connected without any two vertices: no separating 4-cycle of the vertex-face graph."""
    face = materialise(faces(embedding_from_xy(g)))
    if g.vertices.limit(4).count() < 4 or not is_biconnected(g, face):
        return False
    if is_empty(g.degrees().where("degree < 3")):
        vf = vertex_face_graph(g, face)
        vf = TargetGraph(materialise(vf.vertices), vf.edges)
        return is_empty(enumerate_then_separate(vf, cycle(4), vf.vertices.where("label = 'vertex'"), ("vertex", "face") * 2))
    return False


def minimum_vertex_cut(g: TargetGraph) -> list[int] | None:
    """The vertices of some least cut: of a shortest separating cycle's vertices those that aren't faces; None where there is none."""
    face = materialise(faces(embedding_from_xy(g)))
    cut = cut_vertices(g, face).orderBy("id").take(1)
    if cut:
        return [cut[0]["id"]]
    vf = vertex_face_graph(g, face)
    marked = vf.vertices.where("label = 'vertex'")
    for c in (2, 3, 4):
        hit = enumerate_then_separate(vf, cycle(2 * c), marked, ("vertex", "face") * c).orderBy("mapping").take(1)
        if hit:
            return sorted(hit[0]["mapping"][::2])
    return None


def connectivity_bruteforce(edges: list[tuple[int, int]], vertices: list[int]) -> int:
    """Baseline for small graphs: the least set whose removal separates the rest, by trying all of up to five vertices."""
    adj: dict[int, set[int]] = {v: set() for v in vertices}
    for a, b in edges:
        adj[a].add(b)
        adj[b].add(a)
    for c in range(min(6, len(vertices) - 1)):
        if any(separates(adj, set(cut), set(vertices)) for cut in combinations(vertices, c)):
            return c
    return min(len(vertices) - 1, 6)
