"""Layer numbers of trees and their split into paths, by rounds of joins."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coverdp.operators.clustering import uniform
from coverdp.runtime import is_empty, materialise

Unary = tuple[int, int]


def apply_unary(f: Unary, x: int) -> int:
    """h(lo, m): m below lo, m + 1 from lo to m, x above m."""
    lo, m = f
    return m if x < lo else m + 1 if x <= m else x


def compose(outer: Unary, inner: Unary) -> Unary:
    """The member of the family that does `inner` first; the family is closed."""
    (l2, m2), (l1, m1) = outer, inner
    if m2 < m1:
        return l1, m1
    if m2 == m1 or m1 >= l2:
        return 0, m2
    return (l1, m2) if m1 + 1 == l2 else (l2, m2)


def family_closed(cases: DataFrame) -> DataFrame:
    """cases, wrong of cases(l2, m2, l1, m1, x): how often the composed function differs at x from one after the other."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            wrong = [apply_unary(compose((l2, m2), (l1, m1)), x) != apply_unary((l2, m2), apply_unary((l1, m1), x)) for l2, m2, l1, m1, x in zip(*(c.to_pylist() for c in b.columns), strict=True)]
            yield pa.record_batch({"wrong": pa.array(wrong, pa.bool_())})

    rows = cases.select("l2", "m2", "l1", "m1", "x").mapInArrow(run, "wrong boolean")
    return rows.agg(F.count("*").alias("cases"), F.count_if("wrong").alias("wrong"))


def _apply(lo: Column, m: Column, x: Column) -> Column:
    return F.when(lo.isNull(), x).when(x < lo, m).when(x <= m, m + 1).otherwise(x)


def layer_numbers(tree: DataFrame, method: str = "peel", seed: int = 1, most: int = 100_000) -> DataFrame:
    """node, layer of tree(node, parent): leaves 0; else the greatest of the children's, one more where two or more reach it.

    "peel": a node once all its children are known, a round a level. "contract": leaves are raked and chains compressed
    by composing unary functions, a logarithmic number of rounds for any shape; what a chain skipped is filled in last.
    """
    tree = materialise(tree.select("node", "parent"))
    if method == "peel":
        kids = materialise(tree.where("parent is not null").groupBy(F.col("parent").alias("node")).agg(F.count("*").alias("kids")))
        known = materialise(tree.join(kids, "node", "left_anti").select("node", "parent", F.lit(0).alias("layer")))
        front = known
        for _ in range(most):
            ready = known.join(front.select("parent").distinct(), "parent", "left_semi")
            sums = ready.groupBy(F.col("parent").alias("node"), "layer").agg(F.count("*").alias("n"))
            top = sums.groupBy("node").agg(F.sum("n").alias("have"), F.max(F.struct("layer", "n")).alias("t"))
            nxt = top.join(kids, "node").where("have = kids").join(tree, "node").select("node", "parent", (F.col("t.layer") + F.when(F.col("t.n") > 1, 1).otherwise(0)).alias("layer"))
            front = materialise(nxt)
            if is_empty(front):
                break
            known = materialise(known.union(front))
        return known.select("node", "layer")
    return _contracted(tree, seed, most)


def _contracted(tree: DataFrame, seed: int, most: int) -> DataFrame:
    # live: nodes of unknown layer; kids: unknown children left; best, ties: of the known ones; lo, m: a composed function above them
    kids = tree.where("parent is not null").groupBy(F.col("parent").alias("node")).agg(F.count("*").alias("kids"))
    live = materialise(tree.join(kids, "node").select("node", "parent", "kids", F.lit(None).cast("int").alias("best"), F.lit(0).cast("long").alias("ties"), F.lit(None).cast("int").alias("lo"), F.lit(None).cast("int").alias("m")))
    fresh = materialise(tree.join(kids, "node", "left_anti").select("node", "parent", F.lit(0).alias("layer")))
    known, skipped = fresh.select("node", "layer"), []
    for r in range(most):
        # rake: known children tell their parents
        told = fresh.where("parent is not null").groupBy(F.col("parent").alias("node"), "layer").agg(F.count("*").alias("n")).groupBy("node").agg(F.sum("n").alias("came"), F.max(F.struct("layer", "n")).alias("t"))
        j = live.join(told, "node", "left")
        after = F.col("kids") - F.coalesce("came", F.lit(0))
        folded = F.col("lo").isNotNull() & F.col("t").isNotNull()  # its one child came: the function gives the layer
        best = F.greatest("best", "t.layer")
        ties = F.when(F.col("best") == best, F.col("ties")).otherwise(0) + F.when(F.col("t.layer") == best, F.col("t.n")).otherwise(0)
        j = materialise(j.select("node", "parent", after.alias("kids"), F.when(folded, _apply(F.col("lo"), F.col("m"), F.col("t.layer"))).alias("direct"), best.alias("best"), F.when(best.isNull(), 0).otherwise(ties).cast("long").alias("ties"), "lo", "m"))
        fresh = materialise(j.where("kids = 0").select("node", "parent", F.coalesce("direct", F.col("best") + F.when(F.col("ties") > 1, 1).otherwise(0)).cast("int").alias("layer")))
        live = j.where("kids > 0").drop("direct")
        known = known.union(fresh.select("node", "layer"))
        # compress: a chain node whose child is a chain node takes over its function, if their coins differ
        one = F.col("kids") == 1
        own = F.when(F.col("lo").isNotNull(), F.col("lo")).when(F.col("ties") > 1, 0).when(F.col("ties") == 1, F.col("best"))
        live = live.withColumn("lo", F.when(one, own).cast("int")).withColumn("m", F.when(one, F.coalesce("m", "best"))).withColumn("coin", uniform(seed, F.lit(r), F.col("node")) < 0.5)
        live = materialise(live)
        below = live.where(one & ~F.col("coin")).select(F.col("node").alias("c"), F.col("parent").alias("node"), F.col("lo").alias("l1"), F.col("m").alias("m1"))
        pairs = materialise(live.where(one & F.col("coin")).join(below, "node"))
        if is_empty(fresh) and is_empty(live):
            break
        l2, m2, l1, m1 = (F.col(c) for c in ("lo", "m", "l1", "m1"))
        inner = F.struct(l1.alias("lo"), m1.alias("m"))
        zero = F.struct(F.lit(0).alias("lo"), m2.alias("m"))
        both = F.when(l2.isNull(), inner).when(l1.isNull(), F.struct(l2.alias("lo"), m2.alias("m"))).when(m2 < m1, inner).when((m2 == m1) | (m1 >= l2), zero).when(m1 + 1 == l2, F.struct(l1.alias("lo"), m2.alias("m"))).otherwise(F.struct(l2.alias("lo"), m2.alias("m")))
        merged = pairs.select("node", both.alias("f"))
        open_kids = live.select(F.col("node").alias("kid"), F.col("parent").alias("c")).union(fresh.select("node", "parent"))
        skipped.append(materialise(pairs.select("c", F.col("l1").alias("lo"), F.col("m1").alias("m")).join(open_kids, "c")))
        gone = pairs.select(F.col("c").alias("node"), F.col("node").alias("over"))
        live = live.join(gone.select("node"), "node", "left_anti").join(merged, "node", "left").withColumn("lo", F.when(F.col("f").isNotNull(), F.col("f.lo")).otherwise(F.col("lo"))).withColumn("m", F.when(F.col("f").isNotNull(), F.col("f.m")).otherwise(F.col("m"))).drop("f")
        # children of the ones that went hang on the node above
        moved = gone.select(F.col("node").alias("parent"), "over")
        live = live.join(moved, "parent", "left").select("node", F.coalesce("over", "parent").alias("parent"), "kids", "best", "ties", "lo", "m")
        live = materialise(live)
        fresh = materialise(fresh.join(moved, "parent", "left").select("node", F.coalesce("over", "parent").alias("parent"), "layer"))
    known = materialise(known)
    for gone in reversed(skipped):
        # a node that went had one child left, itself known by now: its function gives its layer
        below = known.select(F.col("node").alias("kid"), "layer")
        known = materialise(known.union(gone.join(below, "kid").select(F.col("c").alias("node"), _apply(F.col("lo"), F.col("m"), F.col("layer")).cast("int").alias("layer"))))
    return known


def path_decomposition(tree: DataFrame, layers: DataFrame | None = None) -> DataFrame:
    """node, layer, path (its top node), pos (steps from the top): a child of its parent's layer goes on in its path."""
    layers = layers if layers is not None else layer_numbers(tree)
    up = tree.join(layers, "node").join(layers.select(F.col("node").alias("parent"), F.col("layer").alias("above")), "parent", "left")
    ptr = materialise(up.select("node", "layer", F.when(F.col("layer") == F.col("above"), F.col("parent")).alias("to")).select("node", "layer", F.coalesce("to", "node").alias("to"), F.when(F.col("to").isNull(), 0).otherwise(1).cast("long").alias("pos")))
    while True:
        ahead = ptr.select(F.col("node").alias("to"), F.col("to").alias("further"), F.col("pos").alias("more"))
        nxt = materialise(ptr.join(ahead, "to").select("node", "layer", F.col("further").alias("to"), (F.col("pos") + F.col("more")).alias("pos"), (F.col("more") > 0).alias("moved")))
        moved = not is_empty(nxt.where("moved"))
        ptr = nxt.drop("moved")
        if not moved:
            return ptr.select("node", "layer", F.col("to").alias("path"), "pos")
