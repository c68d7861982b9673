"""Exponential-shift clustering of graphs beyond one task's size: ranges of ids are settled whole, and only vertices at their borders are exchanged.

A block is a range of ids with the edges that touch it; the far ends of those are its ghosts. A pass settles every block
from its own shifts and the ghosts' keys as their blocks last gave them, and gives the keys at its border. Keys only fall, and
when a pass changes none, all are least over paths of the whole graph. Rows are those of the other engines.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.model import TargetGraph
from coverdp.runtime import materialise, release

#: Vertices of a block, about.
BLOCK_IDS = 200_000
#: Keys at borders, of all repetitions, that the driver gathers and sends to every task; more need another engine.
MOST_BORDER = 6_000_000
LOW = (1 << 31) - 1
#: Above all keys, and still so a few steps further.
UNKNOWN = np.int64(1 << 62)
WORK = "block int, n long, ids binary, ghosts binary, a binary, b binary, shift binary"


def _int64(raw) -> np.ndarray:
    return np.frombuffer(raw.as_buffer(), np.int64)


def _int32(raw) -> np.ndarray:
    return np.frombuffer(raw.as_buffer(), np.int32)


def _cuts(g: TargetGraph, n: int) -> np.ndarray:
    parts = max(1, -(-n // BLOCK_IDS))
    if parts == 1:
        return np.zeros(0, np.int64)
    at = g.vertices.select(F.percentile_approx("id", [i / parts for i in range(1, parts)], 10_000)).first()[0]
    return np.unique(np.array(at, np.int64))


def _deal(cuts: np.ndarray):
    """Edges to the block of either end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            src, dst = np.asarray(b.column("src")), np.asarray(b.column("dst"))
            p, q = np.searchsorted(cuts, src), np.searchsorted(cuts, dst)
            two = p != q
            yield pa.record_batch({"block": np.concatenate([p, q[two]]).astype(np.int32), "src": np.concatenate([src, src[two]]), "dst": np.concatenate([dst, dst[two]])})

    return run


def _deal_shifts(cuts: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = np.asarray(b.column("id"))
            shift = b.column("shift").flatten().to_numpy(zero_copy_only=False).astype(np.int32).reshape(len(ids), -1)
            block = np.searchsorted(cuts, ids)
            for own in np.unique(block).tolist():
                mine = block == own
                yield pa.record_batch({"block": pa.array([own], pa.int32()), "ids": pa.array([ids[mine].tobytes()], pa.binary()), "shift": pa.array([shift[mine].tobytes()], pa.binary())})

    return run


def _build(edges: pa.Table, shifts: pa.Table) -> pa.Table:
    """One row of arrays: ids and ghosts rise; a and b number the ends of edges, ghosts after ids; shift is a row a repetition."""
    if not shifts.num_rows:
        return pa.table({"block": pa.array([], pa.int32()), "n": pa.array([], pa.int64())} | {c: pa.array([], pa.binary()) for c in ("ids", "ghosts", "a", "b", "shift")})
    ids = np.concatenate([_int64(x) for x in shifts["ids"]])
    shift = np.concatenate([_int32(x).reshape(len(_int64(y)), -1) for x, y in zip(shifts["shift"], shifts["ids"], strict=True)])
    order = np.argsort(ids)
    ids, shift = ids[order], np.ascontiguousarray(shift[order].T)
    ends = [np.asarray(edges[c], dtype=np.int64) if edges.num_rows else np.zeros(0, np.int64) for c in ("src", "dst")]

    def own(x):
        at = np.minimum(np.searchsorted(ids, x), len(ids) - 1)
        return at, ids[at] == x

    (a, a_own), (b, b_own) = own(ends[0]), own(ends[1])
    ghosts = np.unique(np.concatenate([ends[0][~a_own], ends[1][~b_own]]))
    a = np.where(a_own, a, len(ids) + np.searchsorted(ghosts, ends[0])).astype(np.int32)
    b = np.where(b_own, b, len(ids) + np.searchsorted(ghosts, ends[1])).astype(np.int32)
    raw = {"ids": ids, "ghosts": ghosts, "a": a, "b": b, "shift": shift}
    return pa.table({"block": pa.array([shifts["block"][0].as_py()], pa.int32()), "n": pa.array([len(ids)], pa.int64())} | {c: pa.array([x.tobytes()], pa.binary()) for c, x in raw.items()})


def _solve(shared, offset: int, step: int, first_rep: int, unit: int, emit: Callable):
    """For each block and repetition: settle, and give what `emit` makes of it."""
    from coverdp.operators.clustering import _neighbours, _settle

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        starts, border, known = shared.value
        for batch in batches:
            for row in range(batch.num_rows):
                get = lambda c: batch.column(c)[row]
                block, n = get("block").as_py(), get("n").as_py()
                ids, ghosts, a, b = _int64(get("ids")), _int64(get("ghosts")), _int32(get("a")), _int32(get("b"))
                start = starts[block]
                src, dst = np.concatenate([a, b]), np.concatenate([b, a])
                links = _neighbours(n + len(ghosts), src, dst)
                at = np.searchsorted(border, ghosts)
                rim = np.unique(src[(src < n) & (dst >= n)])
                rim_at = np.searchsorted(border, ids[rim])
                inward = (src >= n) & (dst < n)
                for r, s in enumerate(_int32(get("shift")).reshape(-1, n).astype(np.int64)):
                    own = ((offset - s) << 31) | (start + np.arange(n))
                    table = known[r] if known else None
                    outer = table[0][at] if known else np.full(len(ghosts), UNKNOWN)
                    if emit is _rim and known:
                        now = own.copy()
                        now[rim] = table[0][rim_at]
                        if (outer[src[inward] - n] + step >= now[dst[inward]]).all():  # nothing from outside gets in
                            yield _rim_rows(block, r, ids[rim], *(x[rim_at] for x in table))
                            continue
                    key = _settle(*links, np.concatenate([own, outer]))
                    number = key & LOW
                    inside = (number >= start) & (number < start + n)
                    centre, shift = np.zeros(len(key), np.int64), np.zeros(len(key), np.int64)
                    here = number[inside] - start
                    centre[inside], shift[inside] = ids[here], s[here]
                    if known and not inside.all():
                        names, one = np.unique(outer & LOW, return_index=True)
                        far = np.searchsorted(names, number[~inside])
                        centre[~inside], shift[~inside] = table[1][at[one[far]]], table[2][at[one[far]]]
                    yield from emit(block, r, first_rep + r, n, ids, rim, a, b, s, key, centre, ((key >> 31) - (offset - shift)) // unit, shift)

    return run


def _rim_rows(block, r, ids, key, centre, shift):
    blob = lambda x: pa.array([np.ascontiguousarray(x).tobytes()], pa.binary())
    return pa.record_batch({"block": pa.array([block], pa.int32()), "r": pa.array([r], pa.int32()), "ids": blob(ids), "key": blob(key), "centre": blob(centre), "shift": blob(shift)})


def _rim(block, r, rep, n, ids, rim, a, b, s, key, centre, level, shift):
    yield _rim_rows(block, r, ids[rim], key[rim], centre[rim], shift[rim])


def _rows(block, r, rep, n, ids, rim, a, b, s, key, centre, level, shift):
    for i in range(0, n, 50_000):
        z = min(n, i + 50_000)
        yield pa.record_batch({"rep": np.full(z - i, rep, np.int32), "id": ids[i:z], "center": centre[i:z], "level": level[i:z].astype(np.int32), "shift": s[i:z]})


def _rows_cut(block, r, rep, n, ids, rim, a, b, s, key, centre, level, shift):
    crosses = key[a] & LOW != key[b] & LOW
    cut = np.zeros(len(key), bool)
    cut[a[crosses]] = cut[b[crosses]] = True
    at = 0
    for rows in _rows(block, r, rep, n, ids, rim, a, b, s, key, centre, level, shift):
        yield rows.append_column("cut", pa.array(cut[at : at + rows.num_rows]))
        at += rows.num_rows


def _counts(block, r, rep, n, ids, rim, a, b, s, key, centre, level, shift):
    mine = a < n  # an edge counts in the block of its lesser end
    crosses = int((key[a[mine]] & LOW != key[b[mine]] & LOW).sum())
    yield pa.record_batch({"rep": pa.array([rep], pa.int32()), "crosses": pa.array([crosses], pa.int64()), "edges": pa.array([int(mine.sum())], pa.int64()), "top": pa.array([int(level[:n].max())], pa.int32())})


ROWS = "rep int, id long, center long, level int, shift long"
OUT = {_rows: ROWS, _rows_cut: ROWS + ", cut boolean", _counts: "rep int, crosses long, edges long, top int"}


def settled(g: TargetGraph, shift: Callable, beta: float, reps: int, first_rep: int = 0, counts: bool = False, cut: bool = False) -> DataFrame | None:
    """The clusters of all repetitions, or with `counts` the crossing edges, edges and highest level by block; None if borders are too large.

    cut: a further column of that name, whether the vertex is an end of an edge between two clusters.

    shift(rep) is a column over the vertices.
    """
    from coverdp.operators.clustering import HEX, UNIT

    offset = math.ceil((HEX * math.log(16) + 1) * beta * UNIT)
    if offset >= 1 << 31:
        return None
    spark, n = g.spark, g.vertices.count()
    cuts = _cuts(g, n)
    edges = g.edges.select("src", "dst").mapInArrow(_deal(cuts), "block int, src long, dst long")
    shifts = g.vertices.select("id", F.array(*(shift(first_rep + r) for r in range(reps))).alias("shift")).mapInArrow(_deal_shifts(cuts), "block int, ids binary, shift binary")
    work = materialise(edges.groupBy("block").cogroup(shifts.groupBy("block")).applyInArrow(_build, WORK))
    starts, total = {}, 0
    for row in work.select("block", "n").orderBy("block").collect():
        starts[row["block"]], total = total, total + row["n"]
    border, known = np.zeros(0, np.int64), []
    step = UNIT << 31

    def one_pass(emit, schema):
        shared = spark.sparkContext.broadcast((starts, border, known))
        return work.mapInArrow(_solve(shared, offset, step, first_rep, UNIT, emit), schema)

    if len(starts) > 1:
        size = work.select(F.sum(F.length("ghosts") / 8)).first()[0]
        if size * reps > MOST_BORDER:
            release(work)
            return None
        while True:
            got = one_pass(_rim, "block int, r int, ids binary, key binary, centre binary, shift binary").toArrow().sort_by([("r", "ascending"), ("block", "ascending")])
            by_rep = [[] for _ in range(reps)]
            for r, *raw in zip(got["r"].to_pylist(), *(got[c] for c in ("ids", "key", "centre", "shift")), strict=True):
                by_rep[r].append([_int64(x) for x in raw])
            new = [[np.concatenate(x) for x in zip(*own, strict=True)] for own in by_rep]
            border, before, known = new[0][0], known, [x[1:] for x in new]
            if before and all(np.array_equal(x[0], y[0]) for x, y in zip(before, known, strict=True)):
                break
    emit = _counts if counts else _rows_cut if cut else _rows
    out = materialise(one_pass(emit, OUT[emit]))
    release(work)
    return out
