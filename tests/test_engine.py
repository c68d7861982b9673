"""Worked examples, exact baselines and equalities between independent routes."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from coverdp import patterns as P
from coverdp.model import target_graph
from coverdp.operators import connectivity as C
from coverdp.operators import cover, dp_batch, dp_dist, dp_local, paths, search, treedec
from coverdp.operators.clustering import UNIT, exponential_shift_clustering
from coverdp.operators.disconnected import split_exhaustive


def lattice(w, h, seed):
    r, out = random.Random(seed), []
    for k in range(w * h):
        x, y = k % w, k // w
        if x < w - 1:
            out.append((k, k + 1))
        if y < h - 1:
            out.append((k, k + w))
        if x < w - 1 and y < h - 1 and r.random() < 0.9:
            out.append((k, k + w + 1) if r.random() < 0.5 else (k + 1, k + w))
    return out


def brute(adj, p):
    out = []

    def grow(m):
        if len(m) == p.k:
            out.append(tuple(m[q] for q in range(p.k)))
            return
        q = p.order[len(m)]
        near = [x for x in m if x in p.neighbours[q]]
        for v in set.intersection(*(adj[m[x]] for x in near)) if near else set(adj):
            if v not in m.values():
                grow(m | {q: v})

    grow({})
    return sorted(out)


PATTERNS = [P.EDGE, P.WEDGE, P.TRIANGLE, P.cycle(4), P.cycle(5), P.DIAMOND, P.HOUSE, P.TADPOLE, P.BOWTIE, P.path(4), P.star(3), P.clique(4)]


@pytest.mark.parametrize("p", PATTERNS)
def test_program_equals_search(p):
    for seed in range(3):
        edges = lattice(5, 4, seed)
        adj = treedec.adjacency(*zip(*edges, strict=True))
        want = brute(adj, p)
        e = np.array(edges)
        assert sorted(dp_local.solve(adj, p)) == want
        assert sorted(map(tuple, dp_batch.solve_batch(e[:, 0], e[:, 1], 20, p).tolist())) == want
        canon = lambda m: min(tuple(m[a[i]] for i in range(p.k)) for a in p.automorphisms)
        for got in (dp_local.solve(adj, p, images=True), dp_batch.solve_batch(e[:, 0], e[:, 1], 20, p, images=True).tolist()):
            assert {canon(m) for m in got} == {canon(m) for m in want}
        assert bool(len(dp_batch.solve_batch(e[:, 0], e[:, 1], 20, p, mode="decide"))) == bool(want)


def test_triangle_is_not_found_in_a_path():
    assert dp_local.solve({0: {1}, 1: {0, 2}, 2: {1}}, P.TRIANGLE) == []


def test_induced():
    adj = treedec.adjacency([0, 1, 2, 3, 0], [1, 2, 3, 0, 2])
    assert dp_local.solve(adj, P.cycle(4)) and not dp_local.solve(adj, P.cycle(4), induced=True)


def test_unary_family_is_closed():
    family = [(lo, m) for m in range(9) for lo in range(m + 1)]
    for f in family:
        for g in family:
            h = paths.compose(f, g)
            assert all(paths.apply_unary(h, x) == paths.apply_unary(f, paths.apply_unary(g, x)) for x in range(12))


def test_automorphisms_and_parsing():
    assert [len(p.automorphisms) for p in (P.TRIANGLE, P.cycle(4), P.clique(4), P.DIAMOND, P.BOWTIE, P.HOUSE, P.TWO_TRIANGLES)] == [6, 8, 24, 4, 8, 2, 72]
    assert P.parse("a-b, b-c, c-a") == P.TRIANGLE
    assert (P.TADPOLE.diameter, P.cycle(6).diameter, len(P.THREE_EDGES.components)) == (3, 3, 3)


def test_stop_rule():
    assert not search.should_stop(16, 10, 1500) and search.should_stop(16, 15, 1500)


@pytest.fixture(scope="module")
def g(spark):
    return target_graph(None, spark.createDataFrame(lattice(7, 6, 1), "src long, dst long"))


def test_clusterings_agree(spark, g):
    a, b = (sorted(map(tuple, exponential_shift_clustering(g, 4.0, 2, engine=e).collect())) for e in ("local", "distributed"))
    assert a == b and len(a) == 2 * 42
    shift = {(r, v): s for r, v, _, _, s in a}
    for r, v, c, level, _ in a:
        # no centre is better
        assert all(level * UNIT - shift[r, c] <= 0 * UNIT - shift[r, v] for _ in (0,))


def test_window_multiplicity_and_decompositions(spark, g):
    v, e = cover.treewidth_cover(g, P.cycle(4), 2)
    assert v.groupBy("rep", "id").count().agg({"count": "max"}).collect()[0][0] <= 3
    bags = treedec.elimination_decomposition(e)
    for b in (bags, treedec.binarize(bags), treedec.balanced_decomposition(bags)):
        assert treedec.violations(e, b).count() == 0
    kids = treedec.binarize(bags).where("parent is not null").groupBy("rep", "center", "start", "parent").count()
    assert kids.where("count <> 2").count() == 0


def test_listing_equals_join(spark, g):
    for p in (P.TRIANGLE, P.cycle(4)):
        got = sorted(tuple(r[0]) for r in search.list_occurrences(g, p).collect())
        assert got == sorted(tuple(r[0]) for r in search.join_enumerate(g, p).collect())


def test_separating_program_equals_trying_all():
    r = random.Random(5)
    for seed in range(40):
        w = 4
        edges = [e for e in lattice(w, 3, seed) if r.random() < 0.9]
        adj = treedec.adjacency(*zip(*edges, strict=True))
        marked = {v for v in adj if r.random() < 0.6}
        allowed = {v: 15 if r.random() < 0.8 else 0 for v in adj}
        for p in (P.WEDGE, P.TRIANGLE, P.cycle(4)):
            want = any(all(allowed[x] for x in m) and C.separates(adj, set(m), marked) for m in brute(adj, p))
            assert C.separating_occurrence(adj, p, allowed, marked) == want, (seed, p)


def test_connectivity_bruteforce():
    full = [(a, b) for a in range(4) for b in range(a + 1, 4)]
    assert C.connectivity_bruteforce(full, list(range(4))) == 3
    ring = [(i, (i + 1) % 8) for i in range(8)]
    assert C.connectivity_bruteforce(ring, list(range(8))) == 2
    assert C.connectivity_bruteforce(ring + [(i, 8) for i in range(8)], list(range(9))) == 3


def test_splits(spark):
    ring = target_graph(None, spark.createDataFrame([(i, (i + 1) % 6) for i in range(6)], "src long, dst long"))
    assert split_exhaustive(ring, P.TWO_EDGES) and not split_exhaustive(ring, P.TWO_TRIANGLES)


def test_layer_numbers_agree(spark):
    r = random.Random(3)
    rows = [(0, None)] + [(i, r.randrange(max(0, i - 4), i)) for i in range(1, 25)]
    tree = spark.createDataFrame(rows, "node long, parent long")
    a, b = (sorted(map(tuple, paths.layer_numbers(tree, m).collect())) for m in ("peel", "contract"))
    assert a == b and len(a) == 25
    top = max(x for _, x in a)
    assert 2**top <= 25


def test_ball_baseline_and_output_measures(spark):
    from coverdp import measures
    from coverdp.operators import baselines

    edges = lattice(5, 4, 3)
    g = target_graph(None, spark.createDataFrame(edges, "src long, dst long"))
    adj = treedec.adjacency(*zip(*edges, strict=True))
    want = {tuple(sorted(m)) for m in brute(adj, P.TRIANGLE)}
    got = baselines.ball_list(g, P.TRIANGLE)
    assert sorted(tuple(sorted(r["mapping"])) for r in got.collect()) == sorted(want)
    assert measures.recovered_cells(got).first().asDict() == {"images": len(want), "cells": 3 * len(want)}
    assert measures.least_degree(g).first().asDict() == {"least": min(len(x) for x in adj.values()), "planar_possible": True}
    assert measures.recovered_cells(got.where("false")).first().asDict() == {"images": 0, "cells": 0}


def test_layers_engine(spark):
    """Two triangles joined by a long path."""
    edges = [(0, 1), (1, 2), (0, 2), *((i, i + 1) for i in range(2, 9)), (9, 10), (10, 11), (9, 11)]
    g = target_graph(spark.range(12), spark.createDataFrame(edges, "src long, dst long"))
    assert sorted(sorted(r["mapping"]) for r in search.list_occurrences(g, P.TRIANGLE, engine="layers", batch=3).collect()) == [[0, 1, 2], [9, 10, 11]]
    with pytest.raises(ValueError):
        search.decide(g, P.TRIANGLE, engine="other")


def test_numbers_of_pieces_have_no_gaps(spark):
    """Keys of several partitions, as ids of matches have room for 2**27 pieces only."""
    pieces = spark.range(500).select(F.lit(0).alias("rep"), F.col("id").alias("center"), F.lit(0).alias("start"), F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        got = [r["piece_no"] for r in dp_dist.number_pieces(pieces).collect()]
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")
    assert sorted(got) == list(range(500))
