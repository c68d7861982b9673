"""The block search of proximity graphs against the definition, pair by pair."""

import math
import time

import numpy as np
import pytest

from coverdp.sources import graphs as G


def by_definition(rows, kind):
    out = []
    with np.errstate(invalid="ignore"):
        for a, ax, ay in rows:
            for b, bx, by in rows:
                if a >= b:
                    continue
                r = np.array([(x, y) for i, x, y in rows if i not in (a, b)], float).reshape(-1, 2)
                p, q, c = r - (ax, ay), r - (bx, by), np.subtract((ax, ay), (bx, by))
                most = c[0] * c[0] + c[1] * c[1]
                dot = p[:, 0] * q[:, 0] + p[:, 1] * q[:, 1] < 0
                lune = (p[:, 0] ** 2 + p[:, 1] ** 2 < most) & (q[:, 0] ** 2 + q[:, 1] ** 2 < most)
                if not (dot if kind == "disc" else lune).any():
                    out.append((a, b))
    return sorted(out)


def clouds():
    r = np.random.default_rng(5)
    yield "normal", r.normal(size=(180, 2)).astype(np.float32)
    yield "grid", np.array([(x, y) for x in range(12) for y in range(10)], float)
    yield "line", np.array([(3 * x, x) for x in range(90)], float)
    yield "ring", np.array([(math.cos(t), math.sin(t)) for t in np.arange(80) * (math.pi / 40)])
    yield "copies", np.repeat(r.normal(size=(30, 2)).astype(np.float32), 4, axis=0)
    yield "one place", np.zeros((70, 2))
    yield "clumps", np.concatenate([r.normal(size=(60, 2)) * 1e-6, r.normal(size=(60, 2)) + 1e3])
    yield "nowhere", np.concatenate([r.normal(size=(40, 2)), [(math.nan, 1), (math.nan, math.nan)]])
    yield "infinite", np.concatenate([r.normal(size=(40, 2)), [(math.inf, 1), (-math.inf, math.inf)]])
    yield "two", np.array([(0.0, 1), (2, 3)])
    yield "single", np.array([(0.0, 1)])


@pytest.mark.parametrize("name,xy", list(clouds()), ids=lambda x: x if isinstance(x, str) else "")
@pytest.mark.parametrize("kind", ["disc", "lune"])
def test_edges_are_those_of_the_definition(spark, name, xy, kind):
    ids = np.random.default_rng(1).permutation(len(xy)).tolist()
    rows = [(i, float(x), float(y)) for i, (x, y) in zip(ids, xy, strict=True)]
    pts = spark.createDataFrame(rows, "id long, x double, y double")
    got = G._proximity(pts, G._in_disc if kind == "disc" else G._in_lune).collect()
    assert sorted(map(tuple, got)) == by_definition(rows, kind)


def test_many_points_take_seconds(spark):
    # sorting all points anew for each took minutes at this size
    xy = np.random.default_rng(2).normal(size=(40_000, 2))
    pts = spark.createDataFrame([(i, float(x), float(y)) for i, (x, y) in enumerate(xy)], "id long, x double, y double").cache()
    pts.count()
    begin = time.monotonic()
    m = G._proximity(pts, G._in_disc).count()
    assert time.monotonic() - begin < 60
    assert 1.9 * len(xy) < m < 2.1 * len(xy)
