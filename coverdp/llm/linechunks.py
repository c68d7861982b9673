"""Removal of globally repeated runs of lines, found by all their windows of two lines."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.llm.textkit import WHITE, col, slices, span_hashes, text_bytes
from coverdp.runtime import materialise

#: At most so many groups are sent to all tasks, some hundreds of kilobytes.
HOT = 4096


def _windows(data: np.ndarray, offs: np.ndarray):
    """(first byte, end, end without line break, first line, last line, text) of each two neighbouring lines of a text.

    Lines of white space alone don't count as lines; those between two others belong to the window.
    """
    breaks = np.flatnonzero(data == 10) + 1
    edges = np.unique(np.concatenate([offs, breaks[breaks < len(data)]]))
    starts, ends = edges[:-1], edges[1:]
    text = np.searchsorted(offs, starts, "right") - 1
    bare = ends - (data[np.maximum(ends - 1, 0)] == 10) if len(data) else ends
    ink = np.concatenate([[0], np.cumsum(~WHITE[data])])
    full = np.flatnonzero(ink[ends] > ink[starts])
    a, z = full[:-1], full[1:]
    same = text[a] == text[z]
    a, z = a[same], z[same]
    number = np.arange(len(starts)) - np.searchsorted(text, text, "left")
    return starts[a], ends[z], bare[z], number[a], number[z], text[a]


def _table(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for b in slices(whole, "text"):
            data, offs = text_bytes(col(b, "text"))
            s, e, bare, line, last, text = _windows(data, offs)
            if len(s):
                h1, h2 = span_hashes(data, s, bare), span_hashes(data[::-1], len(data) - bare, len(data) - s, 99)
                yield pa.record_batch({"doc_id": col(b, "doc_id").take(pa.array(text)), "at": s - offs[text], "stop": e - offs[text], "line": line, "last": last, "h1": h1.view(np.int64), "h2": h2.view(np.int64)})


def _bytes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for b in slices(whole, "text"):
            h1, h2, raw = [], [], []
            for text, spans in zip(col(b, "text").to_pylist(), col(b, "spans").to_pylist(), strict=True):
                own = (text or "").encode()
                for x in spans:
                    h1.append(x["h1"]), h2.append(x["h2"]), raw.append(own[x["at"] : x["stop"]].removesuffix(b"\n"))
            yield pa.record_batch({"h1": pa.array(h1, pa.int64()), "h2": pa.array(h2, pa.int64()), "raw": pa.array(raw, pa.binary())})


def _cut(name: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for text, spans in zip(col(b, "text").to_pylist(), col(b, name).to_pylist(), strict=True):
                if spans:
                    own, at, kept = (text or "").encode(), 0, []
                    for x in sorted(spans, key=lambda x: x["at"]):
                        kept.append(own[at : x["at"]])
                        at = max(at, x["stop"])
                    text = b"".join([*kept, own[at:]]).decode(errors="ignore")
                out.append(text)
            i = b.schema.get_field_index("text")
            yield b.set_column(i, b.schema.field(i).with_type(pa.string()), pa.array(out, pa.string()))

    return run


def _members(chunks: DataFrame, groups: DataFrame) -> DataFrame:
    """Each window of a group with its group. Groups with at least one in HOT of all windows meet theirs by broadcast.

    There are at most HOT such groups whatever the corpus, so a window that a third of all documents hold isn't dealt to one task.
    """
    common = F.col("copies") * HOT >= chunks.count()
    hot = F.broadcast(groups.where(common))
    rest = chunks.join(hot, ["h1", "h2"], "left_anti").join(groups.where(~common), ["h1", "h2"])
    return chunks.join(hot, ["h1", "h2"]).unionByName(rest)


def repeated_chunks(docs: DataFrame) -> DataFrame:
    """(doc_id, removed_spans, n_chunks, n_removed_lines): the later copies of repeated runs of two lines or more.

    A run repeats where all its windows of two lines do, so every window is looked up (n_chunks of them) and the lines
    of those with an earlier copy by (doc_id, place) go; a copy that overlaps the first one stays. So the first place of
    each line stays. Copies are grouped by a 128-bit hash, then the least and the greatest bytes of each group are
    compared; groups where they differ lose nothing. Texts without two lines have no window.
    """
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("text is not null and doc_id is not null")
    chunks = materialise(src.mapInArrow(_table, "doc_id long, at long, stop long, line long, last long, h1 long, h2 long"))
    groups = materialise(chunks.groupBy("h1", "h2").agg(F.count("*").alias("copies"), F.min(F.struct("doc_id", "at", "stop")).alias("first")).where("copies > 1"))
    members = materialise(_members(chunks, groups))
    wanted = members.groupBy("doc_id").agg(F.collect_list(F.struct("at", "stop", "h1", "h2")).alias("spans"))
    raw = src.join(wanted, "doc_id").select("text", "spans").mapInArrow(_bytes, "h1 long, h2 long, raw binary")
    unlike = materialise(raw.groupBy("h1", "h2").agg((F.min("raw") < F.max("raw")).alias("unlike")).where("unlike").select("h1", "h2"))
    gone = members.where("doc_id <> first.doc_id or at >= first.stop").join(unlike, ["h1", "h2"], "left_anti")
    gone = gone.groupBy("doc_id").agg(F.collect_set(F.struct("at", "stop")).alias("removed_spans"), F.size(F.array_distinct(F.flatten(F.collect_list(F.sequence("line", "last"))))).cast("long").alias("n_removed_lines"))
    return chunks.groupBy("doc_id").agg(F.count("*").alias("n_chunks")).join(gone, "doc_id", "left")


def drop_repeated_chunks(docs: DataFrame, names: tuple[str, str] = ("n_chunks", "n_removed_lines")) -> DataFrame:
    """docs with the later copies of repeated runs of lines cut from text, and two counts under `names`; no row goes.

    Null texts stay null, a text that is nothing but later copies becomes empty. Input columns with one of the two
    names are replaced, all others stay. Rows that repeat a doc_id are cut alike; where their texts differ, each loses
    the spans of all of them.
    """
    found = materialise(repeated_chunks(docs))
    base = docs.drop(*names)
    spans = "removed_spans"
    while spans in docs.columns:
        spans += "_"
    mine = found.select(F.col("doc_id"), F.col("n_chunks").alias(f"{spans}a"), F.col("n_removed_lines").alias(f"{spans}b"), F.col("removed_spans").alias(spans))
    counts = (F.coalesce(f"{spans}{x}", F.lit(0)).cast("long").alias(name) for x, name in zip("ab", names, strict=True))
    wide = base.join(mine, "doc_id", "left").select(*base.columns, *counts, spans)
    return wide.mapInArrow(_cut(spans), wide.schema).drop(spans)
