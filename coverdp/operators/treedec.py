"""Tree decompositions of small pieces by elimination, their binary form and their checks."""

from __future__ import annotations

import heapq
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.operators.cover import PIECE
from coverdp.runtime import materialise

BAGS = "rep int, center long, start int, node int, parent int, bag array<long>"


def eliminate(adj: dict[int, set[int]], rule: str = "degree") -> list[tuple[int, list[int], int]]:
    """(vertex, its later neighbours, number of the parent node or -1) in elimination order.

    rule "degree": fewest neighbours next; "fill": fewest missing edges among neighbours next. Ties go to the least id.
    """
    work = {v: set(n) for v, n in adj.items()}

    def cost(v: int) -> int:
        n = work[v]
        return len(n) if rule == "degree" else sum(1 for a in n for b in n if a < b and b not in work[a])

    heap = [(cost(v), v) for v in work]
    heapq.heapify(heap)
    out: list[tuple[int, list[int]]] = []
    while heap:
        c, v = heapq.heappop(heap)
        if v not in work or c != cost(v):
            continue
        near = work.pop(v)
        out.append((v, sorted(near)))
        touched = set(near)
        for a in near:
            work[a].discard(v)
            work[a] |= near - {a}
            if rule != "degree":
                touched |= work[a]
        for a in touched:
            heapq.heappush(heap, (cost(a), a))
    at = {v: i for i, (v, _) in enumerate(out)}
    return [(v, near, min((at[a] for a in near), default=-1)) for v, near in out]


def adjacency(src: Iterable[int], dst: Iterable[int]) -> dict[int, set[int]]:
    adj: dict[int, set[int]] = {}
    for a, b in zip(src, dst, strict=True):
        adj.setdefault(a, set()).add(b)
        adj.setdefault(b, set()).add(a)
    return adj


def by_piece(table: pa.Table, keys: list[str] = PIECE):
    """(key, slice) for each piece of a table that holds several."""
    if not table.num_rows:
        return
    table = table.sort_by([(k, "ascending") for k in keys])
    cols = [np.asarray(table[k]) for k in keys]
    new = np.zeros(table.num_rows, bool)
    new[0] = True
    for c in cols:
        new[1:] |= c[1:] != c[:-1]
    at = np.append(np.flatnonzero(new), table.num_rows)
    for a, z in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        yield tuple(c[a].item() for c in cols), table.slice(a, z - a)


def packed(pieces: DataFrame, rows_each: int = 20_000) -> DataFrame:
    """Pieces with a bucket that several small ones share: about rows_each rows a bucket, and not fewer buckets than keep all cores busy.

    The pieces are written once and counted, so a bucket doesn't grow with the graph; a piece is never split.
    """
    pieces = materialise(pieces)
    buckets = max(4 * pieces.sparkSession.sparkContext.defaultParallelism, -(-pieces.count() // rows_each))
    return pieces.withColumn("bucket", F.pmod(F.xxhash64(*PIECE), F.lit(buckets)).cast("int"))


def elimination_decomposition(piece_edges: DataFrame, rule: str = "degree") -> DataFrame:
    """bags(rep, center, start, node, parent, bag) of each piece: node i is the i-th vertex with its later neighbours."""

    def run(table: pa.Table) -> pa.Table:
        rows = []
        for key, t in by_piece(table):
            for i, (v, near, up) in enumerate(eliminate(adjacency(t["src"].to_pylist(), t["dst"].to_pylist()), rule)):
                rows.append((*key, i, None if up < 0 else up, sorted([v, *near])))
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 6
        kinds = (pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.list_(pa.int64()))
        return pa.table([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=[*PIECE, "node", "parent", "bag"])

    return packed(piece_edges.select(*PIECE, "src", "dst")).groupBy("bucket").applyInArrow(run, BAGS)


def binarize(bags: DataFrame) -> DataFrame:
    """Every inner node has two children: further children hang on copies of the node, empty leaves fill up. Nodes are renumbered, `side` is L or R."""

    def run(table: pa.Table) -> pa.Table:
        rows = []
        for key, t in by_piece(table):
            nodes = {r["node"]: r for r in t.to_pylist()}
            below: dict[int, list[int]] = {}
            for r in nodes.values():
                if r["parent"] is not None:
                    below.setdefault(r["parent"], []).append(r["node"])
            new: list[list] = []

            def put(parent, side, bag):
                new.append([len(new), parent, side, bag])
                return len(new) - 1

            stack = [(i, None, None) for i, r in nodes.items() if r["parent"] is None]
            while stack:
                i, up, side = stack.pop()
                kids, bag = sorted(below.get(i, [])), nodes[i]["bag"]
                at = put(up, side, bag)
                while len(kids) > 2:
                    stack.append((kids.pop(), at, "R"))
                    at = put(at, "L", bag)
                if kids:
                    stack.append((kids[0], at, "L"))
                    if len(kids) == 2:
                        stack.append((kids[1], at, "R"))
                    else:
                        put(at, "R", [])
            rows += [(*key, *r) for r in new]
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 7
        kinds = (pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.string(), pa.list_(pa.int64()))
        return pa.table([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=[*PIECE, "node", "parent", "side", "bag"])

    return packed(bags.select(*PIECE, "node", "parent", "bag")).groupBy("bucket").applyInArrow(run, "rep int, center long, start int, node int, parent int, side string, bag array<long>")


def balanced_decomposition(bags: DataFrame) -> DataFrame:
    """Decompositions of logarithmic height and about three times the width: split at a node that halves the part, carrying the bags at its border."""

    def run(table: pa.Table) -> pa.Table:
        rows = []
        for key, t in by_piece(table):
            nodes = {r["node"]: r for r in t.to_pylist()}
            adj: dict[int, set[int]] = {i: set() for i in nodes}
            for r in nodes.values():
                if r["parent"] is not None:
                    adj[r["node"]].add(r["parent"])
                    adj[r["parent"]].add(r["node"])
            left = set(nodes)
            count = 0
            while left:
                comp = _reach(adj, min(left), left)
                left -= comp
                # (part of the tree, tree edges that leave it as their inner and outer ends, number of the parent)
                stack = [(comp, [], None)]
                while stack:
                    part, border, up = stack.pop()
                    cut = _between(adj, part, [a for a, _ in border]) if len(border) > 1 else _centre(adj, part)
                    bag = set(nodes[cut]["bag"])
                    for a, b in border:
                        bag |= set(nodes[a]["bag"]) & set(nodes[b]["bag"])
                    rows.append((*key, count, up, sorted(bag)))
                    me, count = count, count + 1
                    rest = part - {cut}
                    while rest:
                        sub = _reach(adj, min(rest), rest)
                        rest -= sub
                        own = [(a, b) for a, b in border if a in sub] + [(a, cut) for a in adj[cut] if a in sub]
                        stack.append((sub, own, me))
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 6
        kinds = (pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.list_(pa.int64()))
        return pa.table([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=[*PIECE, "node", "parent", "bag"])

    return packed(bags.select(*PIECE, "node", "parent", "bag")).groupBy("bucket").applyInArrow(run, BAGS)


def _reach(adj: dict[int, set[int]], start: int, within: set[int]) -> set[int]:
    seen, stack = {start}, [start]
    while stack:
        for b in adj[stack.pop()]:
            if b in within and b not in seen:
                seen.add(b)
                stack.append(b)
    return seen


def _centre(adj: dict[int, set[int]], part: set[int]) -> int:
    """A node without which no part has over half of the nodes."""
    root = min(part)
    order, up = [root], {root: None}
    for v in order:
        for b in sorted(adj[v]):
            if b in part and b not in up:
                up[b] = v
                order.append(b)
    size = {v: 1 for v in order}
    worst = {v: 0 for v in order}
    for v in reversed(order):
        worst[v] = max(worst[v], len(order) - size[v])
        if up[v] is not None:
            size[up[v]] += size[v]
            worst[up[v]] = max(worst[up[v]], size[v])
    return min(order, key=lambda v: (worst[v], v))


def _between(adj: dict[int, set[int]], part: set[int], ends: list[int]) -> int:
    """Of the path between the first two border nodes, the one that splits the part best: borders never pile up."""
    up, order = {ends[0]: None}, [ends[0]]
    for v in order:
        for b in sorted(adj[v]):
            if b in part and b not in up:
                up[b] = v
                order.append(b)
    path, v = [], ends[1]
    while v is not None:
        path.append(v)
        v = up[v]
    def worst(c):
        rest, most = part - {c}, 0
        while rest:
            sub = _reach(adj, min(rest), rest)
            rest = rest - sub
            most = max(most, len(sub))
        return most
    return min(path, key=lambda c: (worst(c), c))


def violations(piece_edges: DataFrame, bags: DataFrame) -> DataFrame:
    """(rep, center, start, kind, a, b): vertices in no bag, edges in no bag, vertices whose bags aren't connected. None for a valid decomposition."""
    member = bags.select(*PIECE, "node", "parent", F.explode("bag").alias("id"))
    ends = piece_edges.select(*PIECE, F.explode(F.array("src", "dst")).alias("id")).distinct()
    lost = ends.join(member, [*PIECE, "id"], "left_anti").select(*PIECE, F.lit("vertex").alias("kind"), F.col("id").alias("a"), F.col("id").alias("b"))
    a, b = member.select(*PIECE, "node", F.col("id").alias("src")), member.select(*PIECE, "node", F.col("id").alias("dst"))
    together = piece_edges.select(*PIECE, "src", "dst").distinct().join(a, [*PIECE, "src"]).join(b, [*PIECE, "node", "dst"]).select(*PIECE, "src", "dst").distinct()
    bare = piece_edges.select(*PIECE, "src", "dst").distinct().join(together, [*PIECE, "src", "dst"], "left_anti").select(*PIECE, F.lit("edge"), "src", "dst")
    up = member.select(*PIECE, F.col("node").alias("parent"), "id")
    links = member.where("parent is not null").join(up, [*PIECE, "parent", "id"]).groupBy(*PIECE, "id").agg(F.count("*").alias("links"))
    apart = member.groupBy(*PIECE, "id").agg(F.count("*").alias("nodes")).join(links, [*PIECE, "id"], "left").where(F.col("nodes") - F.coalesce("links", F.lit(0)) != 1)
    return lost.union(bare).union(apart.select(*PIECE, F.lit("split"), "id", "id"))


def width(bags: DataFrame) -> DataFrame:
    return bags.groupBy(*PIECE).agg((F.max(F.size("bag")) - 1).alias("width"))
