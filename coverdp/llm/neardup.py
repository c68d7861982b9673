"""Near-duplicate documents by chosen-path set similarity join."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.llm.similar import Paths, fingerprint, link, signature
from coverdp.llm.textkit import LOWER, col, shingles, slices, span_hashes, text_bytes, words
from coverdp.runtime import materialise


def _sets(batch: pa.RecordBatch, k: int):
    """The distinct shingle hashes of each row's text, in rising order."""
    data, offs = text_bytes(col(batch, "text"))
    data = LOWER[data]
    starts, ends, first = words(data, offs)
    hashes, begin = shingles(span_hashes(data, starts, ends), first, k)
    for i in range(batch.num_rows):
        part = hashes[begin[i] : begin[i + 1]]
        yield np.unique(part)


def _summaries(k: int, n: int):
    def run(batches):
        for whole in batches:
            for b in slices(whole, "text"):
                size, f1, f2, sig = [], [], [], []
                for s in _sets(b, k):
                    one, two = fingerprint(s)
                    size.append(len(s)), f1.append(one), f2.append(two), sig.append(signature(s, n) if len(s) else b"")
                yield pa.record_batch({"doc_id": col(b, "doc_id"), "n": pa.array(size, pa.int64()), "f1": pa.array(f1, pa.int64()), "f2": pa.array(f2, pa.int64()), "sig": pa.array(sig, pa.binary())})

    return run


def _full(k: int):
    def run(batches):
        for whole in batches:
            for b in slices(whole, "text"):
                yield pa.record_batch({"rid": col(b, "doc_id"), "tokens": pa.array([s.tobytes() for s in _sets(b, k)], pa.binary())})

    return run


def near_duplicates(docs: DataFrame, shingle_words: int = 2, paths: Paths = Paths()) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of docs(doc_id, text).

    Links two documents when 100 * intersection >= percent * union of their shingle sets (words split at white space,
    A-Z lower-cased); components are transitive. Texts without words, empty and null texts have no shingles and stand
    alone. Equal sets are one class before any comparison. Rows that repeat a doc_id give one row each, with the
    same component only if their texts are linked. Rows with a null doc_id get a null component and are kept.
    """
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    summary = materialise(src.mapInArrow(_summaries(shingle_words, paths.coordinates), "doc_id long, n long, f1 long, f2 long, sig binary"))
    able = summary.where("n > 0 and doc_id is not null")
    classes = materialise(able.groupBy("f1", "f2", "n").agg(F.min("doc_id").alias("rid"), F.min_by("sig", "doc_id").alias("sig")))

    def full_sets(ids: DataFrame) -> DataFrame:
        mine = src.join(ids.withColumnRenamed("rid", "doc_id"), "doc_id")
        return mine.mapInArrow(_full(shingle_words), "rid long, tokens binary").dropDuplicates(["rid"])

    linked = link(classes.dropDuplicates(["rid"]), full_sets, paths)
    labelled = classes.select("f1", "f2", "n", "rid").join(linked, "rid", "left").select("f1", "f2", "n", F.coalesce("component", "rid").alias("component"))
    out = summary.select("doc_id", "n", "f1", "f2").join(labelled, ["f1", "f2", "n"], "left")
    component = F.when(F.col("n") > 0, F.coalesce("component", "doc_id")).otherwise(F.col("doc_id"))
    return out.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def drop_near_duplicates(docs: DataFrame, shingle_words: int = 5, paths: Paths = Paths()) -> DataFrame:
    """The rows of docs whose document is the least of its component; all columns stay."""
    verdict = near_duplicates(docs, shingle_words, paths).where("not kept").select("doc_id").distinct()
    return docs.join(verdict, "doc_id", "left_anti").select(*docs.columns)
