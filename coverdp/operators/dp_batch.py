"""The program of dp_local for all pieces of a task at once: tables of partial matches as arrays, a layer of the trees a step.

A row is a partial match at a node; columns hold the vertex of each pattern vertex, bit masks tell what is mapped within
the bag and what lies below. Rows keep the vertices below too, so a complete row is an occurrence and nothing is walked
top-down; in bounded degree that costs a constant factor of rows. To decide, rows that agree in the bag are merged.
A row counts as found at the node whose own vertex it uses, or where something is below: once, that is.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from coverdp.operators.treedec import eliminate
from coverdp.patterns import Pattern

#: Two-hop pairs that are tabulated at most; beyond, distant pairs aren't pruned.
MOST_PAIRS = 4_000_000
M = np.uint64(0x9E3779B97F4A7C15)


@dataclass
class Rows:
    node: np.ndarray
    at: np.ndarray
    mapped: np.ndarray
    below: np.ndarray

    def __len__(self) -> int:
        return len(self.node)

    def take(self, which: np.ndarray) -> Rows:
        return Rows(self.node[which], self.at[which], self.mapped[which], self.below[which])


def stack(parts: list[Rows]) -> Rows:
    return Rows(*(np.concatenate([getattr(p, f) for p in parts]) for f in ("node", "at", "mapped", "below"))) if len(parts) > 1 else parts[0]


def _hash(columns: list[np.ndarray]) -> np.ndarray:
    out = np.zeros(len(columns[0]), np.uint64)
    for c in columns:
        out = (out ^ c.astype(np.uint64)) * M
        out ^= out >> np.uint64(29)
    return out


def _within(codes: np.ndarray, code: np.ndarray) -> np.ndarray:
    if not len(codes):
        return np.zeros(len(code), bool)
    return codes[np.minimum(np.searchsorted(codes, code), len(codes) - 1)] == code


class Batch:
    def __init__(self, src: np.ndarray, dst: np.ndarray, n: int, pattern: Pattern, allowed: np.ndarray, rule: str, images: bool, induced: bool) -> None:
        self.n, self.p, self.k, self.induced = n, pattern, pattern.k, induced
        self.all = (1 << pattern.k) - 1
        self.near = np.array([sum(1 << q for q in nb) for nb in pattern.neighbours], np.int64)
        self.rising = pattern.rising if images else frozenset()
        a, b = np.concatenate([src, dst]), np.concatenate([dst, src])
        self.codes = {1: np.unique(a * n + b)}
        ends = self.codes[1]
        a, b = ends // n, ends % n
        degree = np.bincount(a, minlength=n)
        self.allowed = allowed & np.array([sum(1 << p for p, nb in enumerate(pattern.neighbours) if len(nb) <= x) for x in range(int(degree.max(initial=0)) + 1)], np.int64)[degree]
        begin = np.searchsorted(a, np.arange(n + 1))
        last, r = self.codes[1], 2
        while r <= pattern.diameter:
            x, y = last // n, last % n
            many = degree[y]
            if many.sum() > MOST_PAIRS:
                break
            far = b[np.repeat(begin[y], many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)]
            last = np.unique(np.concatenate([last, np.repeat(x, many) * n + far]))
            self.codes[r] = last
            r += 1
        adj: dict[int, set[int]] = {v: set() for v in range(n)}
        for x, y in zip(a.tolist(), b.tolist(), strict=True):
            adj[x].add(y)
        order = eliminate(adj, rule)
        self.own = np.array([v for v, _, _ in order], np.int64)
        self.up = np.array([u for _, _, u in order], np.int64)
        sizes = np.array([len(x) for _, x, _ in order], np.int64)
        self.width = int(sizes.max(initial=0))
        near = np.array([x for _, nb, _ in order for x in nb], np.int64)
        node = np.repeat(np.arange(len(order)), sizes)
        self.near_codes = node * n + near  # sorted: nodes rise, neighbours are sorted
        self.bag = [np.concatenate([[v], nb]).astype(np.int64) for v, nb, _ in order]
        layer = np.zeros(len(order), np.int64)
        rank, kids = np.zeros(len(order), np.int64), np.zeros(len(order), np.int64)
        for i, u in enumerate(self.up.tolist()):
            if u >= 0:
                layer[u] = max(layer[u], layer[i] + 1)
                rank[i] = kids[u]
                kids[u] += 1
        self.layer, self.rank, self.kids = layer, rank, kids

    def close(self, d: int, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        return _within(self.codes[d], x * self.n + y) if d in self.codes else np.ones(len(y), bool)

    def ordered(self, p: int, q: int, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        good = np.ones(len(y), bool)
        if (p, q) in self.rising:
            good &= x < y
        if (q, p) in self.rising:
            good &= y < x
        return good

    def lift(self, rows: Rows) -> Rows:
        """To the parents, with the child's number above the bits of `below`; rows of roots and rows whose vertex may not leave yet end here."""
        keep = self.up[rows.node] >= 0
        row, col = np.nonzero((rows.at == self.own[rows.node][:, None]) & (rows.mapped[:, None] >> np.arange(self.k) & 1).astype(bool))
        mapped, below = rows.mapped.copy(), rows.below.copy()
        keep[row] &= ((mapped[row] | below[row]) & self.near[col]) == self.near[col]
        mapped[row] &= ~(1 << col)
        below[row] |= 1 << col
        if self.p.connected:
            keep &= ~((mapped == 0) & (below != 0))
        return Rows(self.up[rows.node[keep]], rows.at[keep], mapped[keep], below[keep] | rows.node[keep] << self.k)

    def merged(self, rows: Rows) -> Rows:
        """One row of those that differ only below the bag."""
        code = _hash([rows.node, rows.below, *(np.where(rows.mapped >> p & 1, rows.at[:, p] + 1, 0) for p in range(self.k))])
        return rows.take(np.unique(code, return_index=True)[1])

    def join(self, a: Rows, b: Rows, child: np.ndarray, have: np.ndarray) -> Rows:
        """Pairs of rows at the same node that agree on the vertices that both sides know. child: the right side's node, by node; have: sorted codes of the vertices that the left side knows."""

        def shared(r: Rows, left: bool) -> list[np.ndarray]:
            out = []
            for p in range(self.k):
                x = r.at[:, p]
                known = (r.mapped >> p & 1).astype(bool)
                known[known] = _within(self.near_codes, child[r.node[known]] * self.n + x[known]) if left else _within(have, r.node[known] * self.n + x[known])
                out.append(np.where(known, x + 1, 0))
            return out

        sa, sb = shared(a, True), shared(b, False)
        ka, kb = _hash([a.node, *sa]), _hash([b.node, *sb])
        order = np.argsort(kb, kind="stable")
        kb = kb[order]
        lo, n = np.searchsorted(kb, ka, "left"), np.searchsorted(kb, ka, "right")
        n = n - lo
        left = np.repeat(np.arange(len(a)), n)
        right = order[np.arange(len(left)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(lo, n)]
        bits = sum((x > 0).astype(np.int64) << p for p, x in enumerate(sa))
        ok = ((a.mapped[left] | a.below[left]) & (b.mapped[right] | b.below[right])) == bits[left]
        ok &= a.node[left] == b.node[right]
        for x, y in zip(sa, sb, strict=True):
            ok &= x[left] == y[right]
        left, right = left[ok], right[ok]
        at = np.where(a.at[left] >= 0, a.at[left], b.at[right])
        out = Rows(a.node[left], at, a.mapped[left] | b.mapped[right], a.below[left] | b.below[right])
        keep = np.ones(len(at), bool)
        only_a, only_b = a.mapped[left] & ~bits[left], b.mapped[right] & ~bits[left]
        for p in range(self.k):
            for q in range(self.k):
                d = self.p.distances[p][q]
                if p == q or d >= self.k and not self.induced:
                    continue
                both = np.flatnonzero(keep & (only_a >> p & only_b >> q & 1).astype(bool))
                if len(both):
                    u, v = at[both, p], at[both, q]
                    good = self.ordered(p, q, u, v)
                    if d < self.k:
                        good &= self.close(d, u, v)
                    if self.induced and d > 1:
                        good &= ~self.close(1, u, v)
                    keep[both] = good
        return out.take(keep)

    def introduce(self, rows: Rows, vertex: np.ndarray) -> Rows:
        """Each row also with the vertex that is new at its node (-1: none) as any pattern vertex it may stand for."""
        parts = [rows]
        x = vertex[rows.node]
        mask = np.where(x >= 0, self.allowed[np.maximum(x, 0)], 0)
        taken = rows.mapped | rows.below
        for p in range(self.k):
            on = np.flatnonzero((mask >> p & 1 & ~(taken >> p)).astype(bool) & ((rows.below & self.near[p]) == 0))
            for q in range(self.k):
                d = self.p.distances[p][q]
                if p == q or not len(on) or d >= self.k and not self.induced:
                    continue
                here = (rows.mapped[on] >> q & 1).astype(bool)
                own = on[here]
                u, v = x[own], rows.at[own, q]
                good = self.ordered(p, q, u, v)
                if d < self.k:
                    good &= self.close(d, u, v)
                if self.induced and d > 1:
                    good &= ~self.close(1, u, v)
                here[here] = ~good
                on = on[~here]
            if len(on):
                at = rows.at[on].copy()
                at[:, p] = x[on]
                parts.append(Rows(rows.node[on], at, rows.mapped[on] | 1 << p, rows.below[on]))
        return stack(parts)


def solve_batch(src: np.ndarray, dst: np.ndarray, n: int, pattern: Pattern, allowed: np.ndarray | None = None, mode: str = "list", rule: str = "degree", images: bool = False, induced: bool = False, counters: dict | None = None) -> np.ndarray:
    """Mappings into a graph on 0..n-1 (several pieces side by side), one a row. mode "decide": at least one a piece that has any, not all."""
    if not n or not len(src):
        return np.zeros((0, pattern.k), np.int64)
    t = Batch(src, dst, n, pattern, np.full(n, -1, np.int64) if allowed is None else allowed, rule, images, induced)
    found: list[np.ndarray] = []
    by_layer = np.argsort(t.layer, kind="stable")
    edges = np.searchsorted(t.layer[by_layer], np.arange(int(t.layer.max(initial=0)) + 2))
    pending: dict[int, list[Rows]] = {}
    states = triples = 0

    def settle(rows: Rows) -> Rows:
        full = (rows.mapped | rows.below) == t.all
        owned = full & ((rows.below != 0) | (rows.at == t.own[rows.node][:, None]).any(axis=1))
        if owned.any():
            hits = rows.at[owned]
            if induced:
                good = np.ones(len(hits), bool)
                for p in range(t.k):
                    for q in range(p + 1, t.k):
                        if q not in pattern.neighbours[p]:
                            good &= ~t.close(1, hits[:, p], hits[:, q])
                hits = hits[good]
            found.append(hits)
        return rows.take(~owned)

    for layer in range(len(edges) - 1):
        nodes = by_layer[edges[layer] : edges[layer + 1]]
        waiting = stack(pending.pop(layer)) if layer in pending else None
        cur = Rows(nodes, np.full((len(nodes), t.k), -1, np.int64), np.zeros(len(nodes), np.int64), np.zeros(len(nodes), np.int64))
        have = np.zeros(0, np.int64)
        for r in range(int(t.kids[nodes].max(initial=0))):
            child_of = np.full(len(t.own), -1, np.int64)
            kid = np.flatnonzero((t.rank == r) & (t.up >= 0))
            kid = kid[t.layer[t.up[kid]] == layer]
            child_of[t.up[kid]] = kid
            mine = waiting.take(t.rank[waiting.below >> t.k] == r)
            mine = Rows(mine.node, mine.at, mine.mapped, mine.below & t.all)
            touched = child_of[cur.node] >= 0
            rest, cur = cur.take(~touched), cur.take(touched)
            if r == 0:
                cur = mine  # the left side is the empty match alone
            else:
                cur = t.join(cur, mine, child_of, have)
                triples += len(cur)
            cur = settle(stack([rest, cur]))
            near = np.concatenate([t.bag[i][1:] + t.up[i] * t.n for i in kid]) if len(kid) else np.zeros(0, np.int64)
            have = np.unique(np.concatenate([have, near]))
        fresh = [t.bag[i][~_within(have, i * t.n + t.bag[i])] for i in nodes]
        for j in range(max(map(len, fresh), default=0)):
            vertex = np.full(len(t.own), -1, np.int64)
            own = [(i, f[j]) for i, f in zip(nodes.tolist(), fresh, strict=True) if len(f) > j]
            vertex[[i for i, _ in own]] = [v for _, v in own]
            cur = settle(t.introduce(cur, vertex))
        if counters is not None and len(cur):
            states = max(states, int(np.bincount(cur.node).max()))
        up = t.lift(cur)
        if mode != "list" and len(up):
            up = t.merged(up)
        target = t.layer[up.node]
        for other in np.unique(target).tolist():
            pending.setdefault(other, []).append(up.take(target == other))
    if counters is not None:
        counters["states"] = max(counters.get("states", 0), states)
        counters["triples"] = counters.get("triples", 0) + triples
        counters["width"] = max(counters.get("width", 0), t.width)
        counters["nodes"] = counters.get("nodes", 0) + len(t.own)
    return np.concatenate(found) if found else np.zeros((0, t.k), np.int64)
