"""Functions for SQL and DataFrames: packed matches, ring edges, pattern search by name."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf


@pandas_udf(T.ArrayType(T.IntegerType()))
def decode_match(code: pd.Series, k: pd.Series, base: pd.Series) -> pd.Series:
    """The k digits of a packed partial match, last pattern vertex first: 0 unmatched, 1 below, from 2 on a slot of the bag; given as -1, -2, 0, 1, ..."""

    def digits(c: int, n: int, b: int) -> list[int]:
        out = []
        for _ in range(n):
            c, d = divmod(c, b)
            out.append(d - 2 if d >= 2 else -1 - d)
        return out

    return pd.Series([digits(int(c), int(n), int(b)) for c, n, b in zip(code, k, base, strict=True)])


@udtf(returnType=T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())]))
class RingEdges:
    """The edges of a ring of n vertices."""

    def eval(self, n: int):
        for i in range(n):
            j = (i + 1) % n
            if i != j:
                yield min(i, j), max(i, j)


def register(spark: SparkSession) -> None:
    """decode_match and ring_edges for SQL."""
    spark.udf.register("decode_match", decode_match)
    spark.udtf.register("ring_edges", RingEdges)


def find_pattern(spark: SparkSession, view: str, pattern: str) -> DataFrame:
    """mapping of every image of a pattern such as 'a-b, b-c, c-a' in a view or table of edges (src, dst)."""
    from coverdp.model import target_graph
    from coverdp.operators.search import list_occurrences
    from coverdp.patterns import parse

    return list_occurrences(target_graph(None, spark.table(view)), parse(pattern)).withColumn("mapping", F.col("mapping"))
