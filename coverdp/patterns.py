"""Small pattern graphs: parsing, derived numbers, a catalogue."""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import cached_property
from itertools import combinations, permutations


@dataclass(frozen=True)
class Pattern:
    """An undirected simple graph on 0..k-1; labels restrict what a vertex may be mapped to (None: anything)."""

    k: int
    edges: tuple[tuple[int, int], ...]
    labels: tuple[str | None, ...] | None = None

    def __post_init__(self) -> None:
        if self.k < 1 or any(not (0 <= a < b < self.k) for a, b in self.edges) or len(set(self.edges)) != len(self.edges):
            raise ValueError("edges are distinct pairs a < b of 0..k-1")
        if self.labels is not None and len(self.labels) != self.k:
            raise ValueError("one label a vertex")

    @cached_property
    def neighbours(self) -> tuple[frozenset[int], ...]:
        return tuple(frozenset(b if a == v else a for a, b in self.edges if v in (a, b)) for v in range(self.k))

    def hops(self, start: int) -> dict[int, int]:
        seen, front = {start: 0}, [start]
        while front:
            front = [w for v in front for w in self.neighbours[v] if w not in seen and not seen.update({w: seen[v] + 1})]
        return seen

    @cached_property
    def components(self) -> tuple[tuple[int, ...], ...]:
        left, out = set(range(self.k)), []
        while left:
            own = tuple(sorted(self.hops(min(left))))
            out.append(own)
            left -= set(own)
        return tuple(out)

    @property
    def connected(self) -> bool:
        return len(self.components) == 1

    @cached_property
    def diameter(self) -> int:
        """The largest distance within a component."""
        return max(max(self.hops(v).values()) for v in range(self.k))

    @cached_property
    def automorphisms(self) -> tuple[tuple[int, ...], ...]:
        mine = set(self.edges)
        same = self.labels or (None,) * self.k
        return tuple(p for p in permutations(range(self.k)) if all(same[v] == same[p[v]] for v in range(self.k)) and all((min(p[a], p[b]), max(p[a], p[b])) in mine for a, b in self.edges))

    @cached_property
    def distances(self) -> tuple[tuple[int, ...], ...]:
        """Hops between vertices; k where they aren't connected."""
        return tuple(tuple(self.hops(v).get(w, self.k) for w in range(self.k)) for v in range(self.k))

    @cached_property
    def rising(self) -> frozenset[tuple[int, int]]:
        """Adjacent pairs (p, q) such that asking for a smaller image of p than of q keeps a mapping of every image.

        A vertex is put before its orbit under the automorphisms that fix the earlier choices; of these conditions only
        those between neighbours stay, as neighbours always meet in a bag.
        """
        group, out = self.automorphisms, set()
        while len(group) > 1:
            orbits = {v: {a[v] for a in group} for v in range(self.k)}
            v = max((v for v in orbits if len(orbits[v]) > 1), key=lambda v: (len(orbits[v] & self.neighbours[v]), -v))
            out |= {(v, u) for u in orbits[v] & self.neighbours[v]}
            group = tuple(a for a in group if a[v] == v)
        return frozenset(out)

    def part(self, vertices: tuple[int, ...]) -> Pattern:
        at = {v: i for i, v in enumerate(vertices)}
        return Pattern(len(vertices), tuple(sorted((at[a], at[b]) for a, b in self.edges if a in at and b in at)), self.labels and tuple(self.labels[v] for v in vertices))

    @cached_property
    def order(self) -> tuple[int, ...]:
        """Vertices so that each but a component's first has an earlier neighbour."""
        out: list[int] = []
        for own in self.components:
            out += sorted(own, key=self.hops(max(own, key=lambda v: len(self.neighbours[v]))).__getitem__)
        return tuple(out)


def parse(text: str) -> Pattern:
    """A pattern from "a-b, b-c": names are numbered as they appear; a lone name is a vertex without edges."""
    names: dict[str, int] = {}
    edges = set()
    for part in filter(None, (x.strip() for x in text.split(","))):
        ends = [names.setdefault(x.strip(), len(names)) for x in part.split("-")]
        if len(ends) > 2 or len(set(ends)) < len(ends):
            raise ValueError(f"not an edge: {part}")
        if len(ends) == 2:
            edges.add((min(ends), max(ends)))
    return Pattern(len(names), tuple(sorted(edges)))


def path(k: int, labels: tuple[str | None, ...] | None = None) -> Pattern:
    return Pattern(k, tuple((i, i + 1) for i in range(k - 1)), labels)


def cycle(n: int) -> Pattern:
    return Pattern(n, tuple(sorted((min(i, (i + 1) % n), max(i, (i + 1) % n)) for i in range(n))))


def clique(n: int) -> Pattern:
    return Pattern(n, tuple(combinations(range(n), 2)))


def star(r: int, labels: tuple[str | None, ...] | None = None) -> Pattern:
    return Pattern(r + 1, tuple((0, i) for i in range(1, r + 1)), labels)


def wheel(r: int) -> Pattern:
    rim = cycle(r).edges
    return Pattern(r + 1, tuple(sorted([*rim, *((i, r) for i in range(r))])))


EDGE, WEDGE, TRIANGLE = path(2), path(3), cycle(3)
DIAMOND = Pattern(4, ((0, 1), (0, 2), (1, 2), (1, 3), (2, 3)))
BOWTIE = Pattern(5, ((0, 1), (0, 2), (1, 2), (2, 3), (2, 4), (3, 4)))
HOUSE = Pattern(5, ((0, 1), (0, 3), (0, 4), (1, 2), (1, 4), (2, 3)))
TADPOLE = Pattern(5, ((0, 1), (0, 2), (1, 2), (2, 3), (3, 4)))
TWO_EDGES = Pattern(4, ((0, 1), (2, 3)))
TWO_TRIANGLES = Pattern(6, ((0, 1), (0, 2), (1, 2), (3, 4), (3, 5), (4, 5)))
EDGE_PLUS_WEDGE = Pattern(5, ((0, 1), (2, 3), (3, 4)))
THREE_EDGES = Pattern(6, ((0, 1), (2, 3), (4, 5)))


def beta_for(pattern: Pattern) -> float:
    """Twice the pattern's vertices: an occurrence then stays whole with probability 1/2 at least."""
    return 2.0 * pattern.k


def repetitions(n: int, confidence: float = 1.0) -> int:
    """Runs after which absence is wrong with probability n ** -confidence at most."""
    return max(1, math.ceil(confidence * math.log2(max(n, 2))))
