"""Later repetitions solve only what no earlier one showed."""

import pytest
from pyspark.sql import functions as F

from coverdp import patterns as P
from coverdp.model import target_graph
from coverdp.operators import search
from coverdp.operators.clustering import crossing_edges, exponential_shift_clustering


def grid(spark, w):
    edges = [(k, k + 1) for k in range(w * w) if k % w < w - 1] + [(k, k + w) for k in range(w * (w - 1))]
    edges += [(k, k + w + 1) for k in range(w * (w - 1)) if k % w < w - 1 and k % 3]
    return target_graph(None, spark.createDataFrame(edges, "src long, dst long"))


@pytest.mark.parametrize("engine", ["local", "distributed"])
def test_vertices_near_a_cut(spark, engine):
    g = grid(spark, 9)
    c = exponential_shift_clustering(g, 3.0, 2, engine=engine, near_cut=1).cache()
    cut = {(r["rep"], v) for r in crossing_edges(g, c).where("crosses").collect() for v in (r["src"], r["dst"])}
    arcs = g.arcs.collect()
    want = cut | {(rep, a["dst"]) for a in arcs for rep in (0, 1) if (rep, a["src"]) in cut}
    assert {(r["rep"], r["id"]) for r in c.where("near_cut").collect()} == want
    assert 0 < len(want) < 162


def test_later_repetitions_shrink(spark):
    pieces, _, left = search._pieces(grid(spark, 40), P.cycle(4), 12, 1, "diameter", None, 0)
    size = {r["rep"]: r["count"] for r in pieces.groupBy("rep").count().collect()}
    assert size[0] > 4 * size.get(6, 0) and left.count() < 40 * 40 / 4


@pytest.mark.parametrize("p", [P.TRIANGLE, P.cycle(4), P.cycle(5), P.HOUSE])
@pytest.mark.parametrize("batch", [2, None])
def test_nothing_is_lost(spark, p, batch):
    g = grid(spark, 12)
    want = sorted(tuple(r["mapping"]) for r in search.join_enumerate(g, p).collect())
    assert want and sorted(tuple(r["mapping"]) for r in search.list_occurrences(g, p, batch=batch).collect()) == want


def test_repetitions_are_clustered_in_several_tasks(spark):
    c = exponential_shift_clustering(grid(spark, 6), 4.0, 12, engine="local")
    parts = c.select(F.spark_partition_id().alias("part"), "rep").distinct().collect()
    assert len({r["part"] for r in parts}) > 3 and len(parts) == 12
