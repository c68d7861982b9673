"""Clusters settled by ranges of ids are those of the other engines."""

import random

import pytest

from coverdp import measures
from coverdp.model import target_graph
from coverdp.operators import blocks, clustering
from coverdp.sources import graphs as G


def rows(df):
    return sorted(tuple(r) for r in df.select("rep", "id", "center", "level", "shift").collect())


def test_blocks_and_whole_agree(spark, tiny, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK_IDS", 150)
    lattice = G.order_lattice_graph(spark, tiny)
    r = random.Random(3)
    apart = spark.createDataFrame([(5 * i << 40,) for i in range(400)], "id long")  # some without edges
    loose = target_graph(apart, spark.createDataFrame([(5 * r.randrange(400) << 40, 5 * r.randrange(400) << 40) for _ in range(300)], "src long, dst long"))
    for g, mode in ((lattice, "exact"), (loose, "bucketed")):
        want = clustering.exponential_shift_clustering(g, 6.0, 2, engine="local", first_rep=3, mode=mode)
        assert rows(clustering.exponential_shift_clustering(g, 6.0, 2, engine="blocks", first_rep=3, mode=mode)) == rows(want)


def test_borders_too_large_go_the_other_way(spark, tiny, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK_IDS", 150)
    monkeypatch.setattr(blocks, "MOST_BORDER", 10)
    g = G.nation_ring(spark, tiny)
    monkeypatch.setattr(blocks, "BLOCK_IDS", 3)
    want = clustering.exponential_shift_clustering(g, 3.0, 2, engine="local")
    assert rows(clustering.exponential_shift_clustering(g, 3.0, 2, engine="blocks")) == rows(want)


@pytest.mark.parametrize("beta", [3.0, 12.0])
def test_crossing_counts_by_block(spark, tiny, monkeypatch, beta):
    g = G.order_lattice_graph(spark, tiny)
    want = clustering.crossing_counts(g, beta, 2)
    monkeypatch.setattr(blocks, "BLOCK_IDS", 150)
    monkeypatch.setattr(clustering, "LOCAL_EDGES", 0)
    called = []
    monkeypatch.setattr(clustering, "_distributed", lambda *a: called.append(a))
    assert clustering.crossing_counts(g, beta, 2) == want and not called
    assert measures.crossing_rate(g, beta, 2).first()["metric"] == "crossing_rate"
