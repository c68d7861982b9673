"""Set similarity join by chosen paths over minwise tokens; shared by the document and the paragraph operator.

Records are sets of 64-bit shingle hashes. In each of `trees` independent trees a record goes to one node, given by the
minwise tokens of `depth` coordinates. Every node is compared wholly: small ones in one group, larger ones in blocks, each
against all others of the node. Links are confirmed on full sets. A group first offers each record's smallest plausible
partner, a large one its most central too; what then still lies in different components is compared pair by pair (in
large groups within the task, which gives only links that join components), so no link that a node shows is lost, and
copies are never expanded into all pairs.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.llm.components import components
from coverdp.llm.textkit import U, col, mix
from coverdp.runtime import is_empty, materialise, tidy


@dataclass(frozen=True)
class Paths:
    """trees x depth coordinates; a pair of similarity s meets in a node of some tree with probability 1 - (1 - s^depth)^trees. leaf: records of a small group; block: of half a large one."""

    trees: int = 25
    depth: int = 5
    leaf: int = 48
    block: int = 512
    percent: int = 80

    @property
    def coordinates(self) -> int:
        return self.trees * self.depth

    def recall(self, similarity: float) -> float:
        return 1 - (1 - similarity**self.depth) ** self.trees

    def plausible(self, coordinates: int) -> float:
        """Estimates below this are not confirmed: four standard deviations under the threshold."""
        s = self.percent / 100
        return s - 4 * (s * (1 - s) / coordinates) ** 0.5


def _factors(n: int) -> tuple[np.ndarray, np.ndarray]:
    i = np.arange(1, n + 1, dtype=U)
    return mix(i * U(0xA24BAED4963EE407)) | U(1), mix(i * U(0x9FB21C651E98DF25))


def signature(distinct: np.ndarray, n: int) -> bytes:
    """The minwise token of each coordinate, as 16 bits."""
    mul, add = _factors(n)
    out = np.full(n, 2**64 - 1, U)
    for at in range(0, len(distinct), 1024):
        out = np.minimum(out, ((distinct[None, at : at + 1024] ^ add[:, None]) * mul[:, None]).min(axis=1))
    return (mix(out + add) & U(0xFFFF)).astype(np.uint16).tobytes()


def fingerprint(distinct: np.ndarray) -> tuple[int, int]:
    """Two 64-bit sums over a set."""
    return int(mix(distinct ^ U(0x5851F42D4C957F2D)).sum(dtype=U).astype(np.int64)), int(mix(distinct + U(0x14057B7EF767814F)).sum(dtype=U).astype(np.int64))


def _node_keys(sig: np.ndarray, tree: np.ndarray, start: np.ndarray, depth: int) -> np.ndarray:
    """sig: rows of coordinates; the path of each row's tree down to `depth`."""
    n = sig.shape[1]
    key = mix(tree.astype(U) * U(0xC2B2AE3D27D4EB4F) + U(depth))
    rows = np.arange(len(sig))
    for j in range(depth):
        key = mix(key * U(0x9E3779B97F4A7C15) + sig[rows, (start + j) % n].astype(U))
    return key.view(np.int64)


def _first_level(p: Paths) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The nodes of each record; signatures of another length have trees of their own."""

    def run(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 2000):
                b = whole.slice(at, 2000)
                raw, every = col(b, "sig").to_pylist(), np.asarray(col(b, "rid"))
                length = np.array([len(x) for x in raw])
                for own in np.unique(length).tolist():
                    rows = np.flatnonzero(length == own)
                    sig, ids = np.frombuffer(b"".join(raw[i] for i in rows), np.uint16).reshape(len(rows), -1), every[rows]
                    trees = sig.shape[1] // p.depth
                    for t in range(trees):
                        tree = np.full(len(ids), t + (0 if trees == p.trees else 1000 * trees))
                        yield pa.record_batch({"node": _node_keys(sig, tree, np.full(len(ids), t * p.depth), p.depth), "rid": ids})

    return run


def _met(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by node those whose node has another; a row is held back until the next one is seen."""
    node, rid, known = np.zeros(0, np.int64), np.zeros(0, np.int64), False
    for b in batches:
        node, rid = np.concatenate([node, np.asarray(col(b, "node"))]), np.concatenate([rid, np.asarray(col(b, "rid"))])
        if len(node) < 2:
            continue
        same = node[1:] == node[:-1]
        keep = np.concatenate([[known], same[:-1]]) | same
        yield pa.record_batch({"node": node[:-1][keep], "rid": rid[:-1][keep]})
        node, rid, known = node[-1:], rid[-1:], bool(same[-1])
    if known:
        yield pa.record_batch({"node": node, "rid": rid})


def _groups(records: DataFrame, p: Paths) -> DataFrame:
    """(node, rid) of all nodes with two records or more; nodes beyond `leaf` as all pairs of their blocks."""
    keyed = records.select("rid", "sig").mapInArrow(_first_level(p), "node long, rid long")
    met = materialise(keyed.repartition("node").sortWithinPartitions("node").mapInArrow(_met, "node long, rid long"))
    sizes = met.groupBy("node").agg(F.count("*").alias("size")).where(F.col("size") > p.leaf)
    big = met.join(materialise(sizes), "node", "left")
    blocks = F.ceil(F.col("size") / p.block).cast("int")
    paired = big.where("size is not null").select("node", "rid", blocks.alias("k"), F.pmod(F.xxhash64("rid"), blocks).cast("int").alias("own"))
    paired = paired.select("node", "rid", "k", "own", F.explode(F.sequence(F.lit(0), F.col("k") - 1)).alias("other")).where("other <> own or k = 1")
    paired = paired.select(F.xxhash64("node", F.least("own", "other"), F.greatest("own", "other")).alias("node"), "rid")
    return big.where("size is null").select("node", "rid").union(paired)


GROUP = "members array<long>, adj binary, central array<long>"


def _plausible(p: Paths) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """For each group its members in rising order, a bit matrix of plausible pairs and, if it's large, each member's plausible partner that is most like the whole group."""

    def run(batches):
        for b in batches:
            for group in col(b, "group"):
                group = sorted(group.as_py(), key=lambda g: g["rid"])
                sig = np.frombuffer(b"".join(g["sig"] for g in group), np.uint16).reshape(len(group), -1)
                n = np.array([g["n"] for g in group], float)
                near, least = np.empty((len(group), len(group)), bool), p.plausible(sig.shape[1])
                like = np.empty(len(group))
                for i in range(len(group)):
                    same = (sig == sig[i]).mean(axis=1)
                    near[i], like[i] = same >= least, same.sum()
                near &= np.minimum(n[:, None], n) * 100 >= np.maximum(n[:, None], n) * p.percent
                np.fill_diagonal(near, False)
                live = np.flatnonzero(near.any(axis=1))
                if not len(live):
                    continue
                rid = np.array([group[i]["rid"] for i in live], np.int64)
                near, like = near[np.ix_(live, live)], like[live]
                central = [int(rid[np.where(row, like, -1).argmax()]) for row in near] if len(group) > p.leaf else []
                yield pa.record_batch({"members": pa.array([rid.tolist()], pa.list_(pa.int64())), "adj": pa.array([np.packbits(near).tobytes()], pa.binary()), "central": pa.array([central], pa.list_(pa.int64()))})

    return run


def _matrix(raw: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(raw, np.uint8), count=n * n).reshape(n, n).astype(bool)


def _partners(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(record, partner, whether the smallest): two a member at most."""
    for b in batches:
        lo, hi, least = [], [], []
        for members, raw, central in zip(*(col(b, x).to_pylist() for x in ("members", "adj", "central")), strict=True):
            m = _matrix(raw, len(members))
            for i in range(1, len(members)):
                j = int(m[i, :i].argmax())
                if m[i, j] and j < i:
                    lo.append(members[j]), hi.append(members[i]), least.append(True)
            for x, y in zip(members, central):
                lo.append(min(x, y)), hi.append(max(x, y)), least.append(False)
        if lo:
            yield pa.record_batch({"a": pa.array(lo, pa.int64()), "b": pa.array(hi, pa.int64()), "least": pa.array(least)})


def _still_apart(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        lo, hi = [], []
        for members, raw, own in zip(col(b, "members").to_pylist(), col(b, "adj").to_pylist(), col(b, "own").to_pylist(), strict=True):
            where = {x["rid"]: x["component"] for x in own}
            comp = np.array([where[x] for x in members])
            i, j = np.nonzero(np.triu(_matrix(raw, len(members)), 1) & (comp[:, None] != comp))
            lo += [members[x] for x in i]
            hi += [members[x] for x in j]
        if lo:
            yield pa.record_batch({"a": pa.array(lo, pa.int64()), "b": pa.array(hi, pa.int64())})


def _crossing(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of large groups the members with a plausible partner in another component."""
    for b in batches:
        gid, rid, comp = [], [], []
        for g, members, raw, own in zip(*(col(b, x).to_pylist() for x in ("gid", "members", "adj", "own")), strict=True):
            where = {x["rid"]: x["component"] for x in own}
            c = np.array([where[x] for x in members])
            live = np.flatnonzero((_matrix(raw, len(members)) & (c[:, None] != c)).any(axis=1))
            gid += [g] * len(live)
            rid += [members[x] for x in live]
            comp += c[live].tolist()
        if rid:
            yield pa.record_batch({"gid": pa.array(gid, pa.int64()), "rid": pa.array(rid, pa.int64()), "component": pa.array(comp, pa.int64())})


def _join_within(percent: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Every member's full set against all of its group; the links that join components, fewer than members."""

    def run(batches):
        for b in batches:
            for group in col(b, "group"):
                rid, comp, sets = [], [], []
                for g in group:
                    rid.append(g["rid"].as_py()), comp.append(g["component"].as_py()), sets.append(np.frombuffer(g["tokens"].as_buffer(), U))
                _, code = np.unique(np.concatenate(sets), return_inverse=True)
                n = np.array([len(x) for x in sets])
                begin = np.cumsum(n) - n
                comp, lo, hi = np.unique(comp, return_inverse=True)[1], [], []
                mine = np.zeros(len(code), bool)
                for i in range(len(sets)):
                    apart = comp != comp[i]
                    if not apart.any():
                        continue
                    own = code[begin[i] : begin[i] + n[i]]
                    mine[own] = True
                    inter = np.add.reduceat(mine[code], begin, dtype=np.int64)
                    mine[own] = False
                    for j in np.flatnonzero(apart & (100 * inter >= percent * (n + n[i] - inter))).tolist():
                        if comp[j] != comp[i]:
                            lo.append(min(rid[i], rid[j])), hi.append(max(rid[i], rid[j]))
                            comp[comp == comp[j]] = comp[i]
                if lo:
                    yield pa.record_batch({"a": pa.array(lo, pa.int64()), "b": pa.array(hi, pa.int64())})

    return run


def _confirm(percent: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches):
        for b in batches:
            keep = np.zeros(b.num_rows, bool)
            for i, (x, y) in enumerate(zip(col(b, "sa"), col(b, "sb"), strict=True)):
                u, v = np.frombuffer(x.as_buffer(), U), np.frombuffer(y.as_buffer(), U)
                both = np.concatenate([u, v])
                both.sort()
                inter = int((both[1:] == both[:-1]).sum())
                keep[i] = 100 * inter >= percent * (len(u) + len(v) - inter)
            if keep.any():
                yield pa.record_batch({"a": col(b, "a"), "b": col(b, "b")}).filter(pa.array(keep))

    return run


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    left = pairs.join(sets.select(F.col("rid").alias("a"), F.col("tokens").alias("sa")), "a")
    return left.join(sets.select(F.col("rid").alias("b"), F.col("tokens").alias("sb")), "b").select("a", "b", "sa", "sb").mapInArrow(_confirm(percent), "a long, b long")


def link(records: DataFrame, full_sets: Callable[[DataFrame], DataFrame], p: Paths) -> DataFrame:
    """records(rid, n, sig) of distinct sets; full_sets(ids) gives (rid, tokens) for a table of rids.

    Returns (rid, component) for the records with a link; others stand alone.
    """
    attached = _groups(records, p).join(records.select("rid", "n", "sig"), "rid")
    groups = attached.groupBy("node").agg(F.collect_list(F.struct("rid", "n", "sig")).alias("group")).where(F.size("group") > 1)
    groups = materialise(groups.select("group").mapInArrow(_plausible(p), GROUP).distinct().withColumn("gid", F.xxhash64("members", "adj")))
    tidy(records)
    offered = materialise(groups.mapInArrow(_partners, "a long, b long, least boolean").groupBy("b", "least", F.when(~F.col("least"), F.col("a")).alias("c")).agg(F.min("a").alias("a")))
    first = offered.select("a", "b").distinct()
    needed = groups.select(F.explode("members").alias("rid")).distinct()
    sets = materialise(full_sets(needed))
    links = materialise(_confirmed(first, sets, p.percent))
    joined = components(links)
    own = groups.select("gid", F.explode("members").alias("rid")).join(joined.withColumnRenamed("id", "rid"), "rid", "left")
    own = own.groupBy("gid").agg(F.collect_list(F.struct("rid", F.coalesce("component", "rid").alias("component"))).alias("own"))
    apart = materialise(groups.join(own, "gid").where(F.size(F.array_distinct("own.component")) > 1).select("gid", "members", "adj", "own", (F.size("central") > 0).alias("large")))
    rest = materialise(apart.where("not large").select("members", "adj", "own").mapInArrow(_still_apart, "a long, b long").distinct().join(first, ["a", "b"], "left_anti"))
    crossing = apart.where("large").select("gid", "members", "adj", "own").mapInArrow(_crossing, "gid long, rid long, component long")
    within = crossing.join(sets, "rid").groupBy("gid").agg(F.collect_list(F.struct("rid", "component", "tokens")).alias("group"))
    within = materialise(within.select("group").mapInArrow(_join_within(p.percent), "a long, b long"))
    if is_empty(rest) and is_empty(within):
        return joined.select(F.col("id").alias("rid"), "component")
    more = _confirmed(rest, sets, p.percent).union(within)
    return components(materialise(links.union(more))).select(F.col("id").alias("rid"), "component")
