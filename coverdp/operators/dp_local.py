"""The dynamic program over a tree decomposition, inside one task, for pieces that fit one.

A state maps each pattern vertex to a vertex of the bag, UNMATCHED, or BELOW (matched to a vertex that has left the
bag). A pattern vertex may only go BELOW once all its pattern neighbours are matched: their adjacency was then seen in
a common bag. A state without UNMATCHED is complete; it is taken out at the node
whose own vertex it uses or where something is BELOW, which is one node only.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.operators.dp_batch import solve_batch
from coverdp.operators.cover import PIECE
from coverdp.operators.treedec import adjacency, by_piece, eliminate, packed
from coverdp.patterns import Pattern

UNMATCHED, BELOW = -1, -2
State = tuple[int, ...]


class Cell:
    """A state with the ways to it: base (), (cell,) lifted, (cell, (p, v)) introduced, (left, right) joined."""

    __slots__ = ("full", "ways")

    def __init__(self) -> None:
        self.ways: list[tuple] = []
        self.full: list[dict[int, int]] | None = None

    def first(self) -> dict[int, int]:
        """One assignment that ends in this state."""
        out, stack = {}, [self]
        while stack:
            for x in (c := stack.pop()).ways[0]:
                if isinstance(x, Cell):
                    stack.append(x)
                else:
                    out[x[0]] = x[1]
        return out

    def expand(self) -> list[dict[int, int]]:
        """All assignments that end in this state, the vertices below included."""
        stack = [self]
        while stack:
            c = stack[-1]
            if c.full is not None:
                stack.pop()
                continue
            need = [x for w in c.ways for x in w if isinstance(x, Cell) and x.full is None]
            if need:
                stack += need
                continue
            out: list[dict[int, int]] = []
            for w in c.ways:
                if not w:
                    out.append({})
                elif len(w) == 1:
                    out += w[0].full
                elif isinstance(w[1], Cell):
                    out += [a | b for a in w[0].full for b in w[1].full]
                else:
                    p, v = w[1]
                    out += [a | {p: v} for a in w[0].full]
            c.full = out
            stack.pop()
        return self.full


def lift(state: State, leaving: int, pattern: Pattern) -> State | None:
    """The one state of the parent that this state fits, once `leaving` has left the bag; None if it may not leave yet."""
    if leaving not in state:
        return state
    p = state.index(leaving)
    if any(state[q] == UNMATCHED for q in pattern.neighbours[p]):
        return None
    up = (*state[:p], BELOW, *state[p + 1 :])
    if pattern.connected and max(up) < 0 and UNMATCHED in up:
        return None  # what is unmatched could no longer touch what is matched
    return up


class Near:
    """Vertices within r hops, found when asked for; two pattern vertices can't be mapped further apart than they are."""

    def __init__(self, adj: dict[int, set[int]]) -> None:
        self.balls: list[dict[int, set[int]]] = [{}, adj]

    def ball(self, v: int, r: int) -> set[int]:
        while len(self.balls) <= r:
            self.balls.append({})
        own = self.balls[r]
        if v not in own:
            inner = self.ball(v, r - 1)
            own[v] = inner.union(*(self.balls[1][w] for w in inner))
        return own[v]


def combine(left: State, right: State, pattern: Pattern, near: Near, rising: frozenset = frozenset()) -> State | None:
    """Both states at once; the caller has seen that they agree on shared vertices of the bag."""
    out = []
    for a, b in zip(left, right, strict=True):
        if a == b:
            if a == BELOW:
                return None
            out.append(a)
        elif b == UNMATCHED:
            out.append(a)
        elif a == UNMATCHED:
            out.append(b)
        else:
            return None
    dist = pattern.distances
    for p in range(pattern.k):
        if right[p] >= 0 and left[p] == UNMATCHED:
            for q in range(pattern.k):
                if left[q] >= 0 and right[q] == UNMATCHED:
                    x, y = out[p], out[q]
                    if (dist[p][q] < pattern.k and y not in near.ball(x, dist[p][q])) or (p, q) in rising and x > y or (q, p) in rising and y > x:
                        return None
    return tuple(out)


def introduce(state: State, v: int, pattern: Pattern, near: Near, mask: int, induced: bool = False, rising: frozenset = frozenset()):
    """(p, state) for each pattern vertex that may be mapped to a vertex new in the bag."""
    adj = near.balls[1][v]
    for p in range(pattern.k):
        if state[p] != UNMATCHED or not mask >> p & 1:
            continue
        dist = pattern.distances[p]
        for q, x in enumerate(state):
            if dist[q] == 1:
                if x == BELOW or x >= 0 and (x not in adj or (p, q) in rising and v > x or (q, p) in rising and x > v):
                    break
            elif x >= 0 and (dist[q] < pattern.k and x not in near.ball(v, dist[q]) or induced and x in adj):
                break
        else:
            yield p, (*state[:p], v, *state[p + 1 :])


def _shared_key(state: State, shared: set[int]) -> tuple:
    return tuple(x if x in shared else UNMATCHED for x in state) if shared else ()


def solve(adj: dict[int, set[int]], pattern: Pattern, masks: dict[int, int] | None = None, mode: str = "list", rule: str = "degree", counters: dict | None = None, induced: bool = False, images: bool = False) -> list[tuple[int, ...]]:
    """Mappings of the pattern into a piece: all of them ("list"), one ("find") or at most one as a yes ("decide").

    Vertices of too small a degree for a pattern vertex are never mapped to it. induced: pattern vertices that aren't
    adjacent must be mapped to vertices that aren't. images: one or a few mappings of each image are enough.
    """
    k = pattern.k
    degree = [len(n) for n in pattern.neighbours]
    allowed = {v: sum(1 << p for p in range(k) if degree[p] <= len(n)) & (masks[v] if masks else -1) for v, n in adj.items()}
    order, close = eliminate(adj, rule), Near(adj)
    rising = pattern.rising if images else frozenset()
    tables: list[dict[State, Cell]] = [{} for _ in order]
    kids: list[list[int]] = [[] for _ in order]
    for i, (_, _, up) in enumerate(order):
        if up >= 0:
            kids[up].append(i)
    empty: State = (UNMATCHED,) * k
    found: list[tuple[int, ...]] = []
    states = triples = wide = 0

    def owned(s: State, v: int) -> bool:
        """Complete, and not all of it in the parent's bag, where it would be found again."""
        return UNMATCHED not in s and (BELOW in s or v in s)

    for i, (v, near, _) in enumerate(order):
        base = Cell()
        base.ways.append(())
        cur: dict[State, Cell] = {empty: base}
        have: set[int] = set()
        done: dict[State, Cell] = {}
        for c in kids[i]:
            out_vertex, out_near, _ = order[c]
            lifted: dict[State, Cell] = {}
            for s, cell in tables[c].items():
                up_state = lift(s, out_vertex, pattern)
                if up_state is not None:
                    lifted.setdefault(up_state, Cell()).ways.append((cell,))
            tables[c] = {}
            incoming = set(out_near)
            if not have:
                cur, have = lifted, incoming
                continue
            shared = have & incoming
            index: dict[tuple, list[tuple[State, Cell]]] = {}
            for s, cell in lifted.items():
                index.setdefault(_shared_key(s, shared), []).append((s, cell))
            merged: dict[State, Cell] = {}
            for s, cell in cur.items():
                for t, other in index.get(_shared_key(s, shared), ()):
                    triples += 1
                    both = combine(s, t, pattern, close, rising)
                    if both is not None:
                        (done if owned(both, v) else merged).setdefault(both, Cell()).ways.append((cell, other))
            cur, have = merged, have | incoming
        for x in [v, *near]:
            if x in have:
                continue
            mask = allowed[x]
            if mask:
                more: dict[State, Cell] = {}
                for s, cell in cur.items():
                    for p, t in introduce(s, x, pattern, close, mask, induced, rising):
                        (done if owned(t, v) else more).setdefault(t, Cell()).ways.append((cell, (p, x)))
                cur |= more
            have.add(x)
        for s in [s for s in cur if owned(s, v)]:
            done.setdefault(s, Cell()).ways += cur.pop(s).ways
        states, wide = max(states, len(cur) + len(done)), max(wide, len(near))
        if done:
            for cell in done.values():
                for m in cell.expand() if mode == "list" or induced else [cell.first()]:
                    full = tuple(m[p] for p in range(k))
                    if induced and any(full[q] in adj[full[p]] for p in range(k) for q in range(p + 1, k) if q not in pattern.neighbours[p]):
                        continue
                    found.append(full)
                    if mode != "list":
                        break
                if found and mode != "list":
                    break
            if found and mode != "list":
                break
        tables[i] = cur
    if counters is not None:
        counters["states"] = max(counters.get("states", 0), states)
        counters["triples"] = counters.get("triples", 0) + triples
        counters["width"] = max(counters.get("width", 0), wide)
        counters["nodes"] = counters.get("nodes", 0) + len(order)
    return found


def _mappings(rep: np.ndarray, got: np.ndarray, k: int) -> pa.Table:
    flat = np.ascontiguousarray(got).ravel()
    return pa.table({"rep": pa.array(rep, pa.int32()), "mapping": pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, k, dtype=np.int32)), pa.array(flat, pa.int64()))})


def _one_by_one(table: pa.Table, pattern: Pattern, mode: str, rule: str, first_window: bool, masks: bool, induced: bool, images: bool) -> pa.Table:
    reps, maps = [], []
    for (rep, _, start), t in by_piece(table):
        src, dst = t["src"].to_pylist(), t["dst"].to_pylist()
        allowed = dict(zip(src + dst, t["src_mask"].to_pylist() + t["dst_mask"].to_pylist(), strict=True)) if masks else None
        got = solve(adjacency(src, dst), pattern, allowed, mode, rule, induced=induced, images=images)
        if got and first_window and mode == "list":
            level = dict(zip(src + dst, t["src_level"].to_pylist() + t["dst_level"].to_pylist(), strict=True))
            last = t["last"][0].as_py()
            got = [m for m in got if min(min(level[v] for v in m), last) == start]
        reps += [rep] * len(got)
        maps += got
    return _mappings(np.array(reps, np.int32), np.array(maps, np.int64).reshape(-1, pattern.k), pattern.k)


def solve_pieces(piece_edges: DataFrame, pattern: Pattern, mode: str = "list", rule: str = "degree", first_window: bool = True, masks: bool = False, induced: bool = False, images: bool = False, engine: str = "batch") -> DataFrame:
    """rep, mapping of every occurrence that some piece holds ("list"), or of one a piece ("find").

    piece_edges as the covers give them, with src_mask and dst_mask if masks. first_window: an occurrence is given
    only in the window of its lowest level, or in the last window if that one would have been dropped. engine: "batch"
    (arrays, all pieces of a task together) or "cells" (a table of states for each piece, walked top-down).
    """
    cols = [*PIECE, "src", "dst", "src_level", "dst_level", "last", *(["src_mask", "dst_mask"] if masks else [])]

    def run(table: pa.Table) -> pa.Table:
        if not table.num_rows:
            return pa.table({"rep": pa.array([], pa.int32()), "mapping": pa.array([], pa.list_(pa.int64()))})
        if engine == "cells":
            return _one_by_one(table, pattern, mode, rule, first_window, masks, induced, images)
        col = lambda c: np.asarray(table[c])
        # vertices of all pieces side by side, numbered by piece and id: a smaller number is a smaller id within a piece
        piece = np.unique(np.stack([col(c).astype(np.int64) for c in PIECE], axis=1), axis=0, return_inverse=True)
        number = piece[1].ravel()
        both = np.stack([np.tile(number, 2), np.concatenate([col("src"), col("dst")])], axis=1)
        ends, first, at = np.unique(both, axis=0, return_index=True, return_inverse=True)
        at = at.ravel()
        allowed = np.concatenate([col("src_mask"), col("dst_mask")]).astype(np.int64)[first] if masks else None
        half = len(at) // 2
        got = solve_batch(at[:half], at[half:], len(ends), pattern, allowed, mode, rule, images, induced)
        own = ends[got[:, 0], 0] if len(got) else np.zeros(0, np.int64)
        if first_window and mode == "list" and len(got):
            level = np.concatenate([col("src_level"), col("dst_level")]).astype(np.int64)[first]
            last = np.zeros(len(piece[0]), np.int64)
            last[number] = col("last")
            keep = np.minimum(level[got].min(axis=1), last[own]) == piece[0][own, 2]
            got, own = got[keep], own[keep]
        if mode != "list":
            one = np.unique(own, return_index=True)[1]
            got, own = got[one], own[one]
        return _mappings(piece[0][own, 0].astype(np.int32), ends[got, 1], pattern.k)

    return packed(piece_edges.select(*cols)).groupBy("bucket").applyInArrow(run, "rep int, mapping array<long>")


def piece_measures(piece_edges: DataFrame, pattern: Pattern, rule: str = "degree") -> DataFrame:
    """rep, center, start, width, states, triples, nodes, found of a full listing of each piece."""

    def run(table: pa.Table) -> pa.Table:
        rows = []
        for key, t in by_piece(table):
            c: dict = {}
            got = solve(adjacency(t["src"].to_pylist(), t["dst"].to_pylist()), pattern, None, "list", rule, c)
            rows.append((*key, c["width"], c["states"], c["triples"], c["nodes"], len(got)))
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 8
        kinds = (pa.int32(), pa.int64(), pa.int32(), *(pa.int64(),) * 5)
        return pa.table([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=[*PIECE, "width", "states", "triples", "nodes", "found"])

    return packed(piece_edges.select(*PIECE, "src", "dst")).groupBy("bucket").applyInArrow(run, "rep int, center long, start int, width long, states long, triples long, nodes long, found long")


def label_masks(g_vertices: DataFrame, pattern: Pattern) -> DataFrame:
    """id, mask: the pattern vertices that each vertex may stand for, by label."""
    labels = pattern.labels or (None,) * pattern.k
    free = sum(1 << p for p, x in enumerate(labels) if x is None)
    mask = F.lit(free)
    for name in sorted({x for x in labels if x is not None}):
        mask = mask + F.when(F.col("label") == name, sum(1 << p for p, x in enumerate(labels) if x == name)).otherwise(0)
    return g_vertices.select("id", mask.cast("int").alias("mask"))


Solver = Callable[[DataFrame, Pattern], DataFrame]
