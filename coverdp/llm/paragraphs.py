"""Paragraph near-duplicates by banded MinHash, confirmed by exact Jaccard, removed by components.

Two kinds of paragraphs are compared, each with its own kind: lines of `least_words` words or more, and passages of
`passage_words` words that begin where a text's own words say so, whatever the lines. A passage begins at each word pair
whose hash is the least of REACH pairs on either side, so a piece of text copied into the middle of another line still gives
the same passages.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.llm.similar import Paths, _factors, link
from coverdp.llm.substrings import joined
from coverdp.llm.textkit import LOWER, STEP, U, col, mix, shingles, slices, span_hashes, text_bytes, words
from coverdp.runtime import materialise, tidy

#: A paragraph's id is doc_id * PLACES + 2 * its first word + its kind (0 a line, 1 a passage).
PLACES = 1 << 26
REACH = 16
#: Eight bands of two rows: a pair of lines at similarity 0.8 meets with probability 0.9997.
BANDS = Paths(trees=8, depth=2)
#: Bands of a passage: 0.953 at 0.8 for one; equal passages always meet, and a copied text of many words has several.
PASSAGE_BANDS = 3


def _anchors(hashes: np.ndarray, first: np.ndarray, reach: int) -> np.ndarray:
    """Words at which a passage may begin: of the pairs up to `reach` to either side in the same text the least hash, the leftmost of equals."""
    n = len(hashes)
    if n < 2:
        return np.zeros(0, np.int64)
    pair = np.full(n + 2 * reach, np.iinfo(np.uint64).max, U)
    pair[reach : reach + n - 1] = mix(hashes[:-1] * STEP + hashes[1:]) >> U(1)
    last = first[1:][np.diff(first) > 0] - 1
    pair[reach + last] = np.iinfo(np.uint64).max  # no pair passes a text's end
    text = np.repeat(np.arange(len(first) - 1), np.diff(first))
    own = pair[reach : reach + n]
    best = own < np.iinfo(np.uint64).max
    for d in range(1, reach + 1):
        same = np.zeros(n, bool)
        same[d:] = text[d:] == text[:-d]
        best &= ~same | (own < pair[reach - d : reach - d + n])
        same = np.zeros(n, bool)
        same[:-d] = text[:-d] == text[d:]
        best &= ~same | (own <= pair[reach + d : reach + d + n])
    return np.flatnonzero(best)


class Units:
    """The paragraphs of some texts: text, first word, kind, bytes [at, stop) of the text, and their shingles as ranges [lo, hi) of `hashes`."""

    def __init__(self, batch: pa.RecordBatch, k: int, least: int, passage: int) -> None:
        data, offs = text_bytes(col(batch, "text"))
        low = LOWER[data]
        starts, ends, first = words(low, offs)
        spans = span_hashes(low, starts, ends)
        # a shingle for each word with k - 1 words after it in its text
        self.hashes, begin = shingles(spans, first, k)
        count = np.diff(first)
        place = np.arange(len(starts)) - np.repeat(first[:-1], count)  # of a word in its text
        text = np.repeat(np.arange(len(count)), count)
        edges = np.unique(np.concatenate([offs, np.flatnonzero(data == 10) + 1]))
        head = np.searchsorted(starts, edges)
        size = np.diff(head)
        line = np.flatnonzero(size >= max(least, k))
        w = head[:-1][line]
        parts = [(text[w], place[w], np.zeros(len(w), np.int64), edges[line], edges[line + 1], size[line] - k + 1)]
        a = _anchors(spans, first, REACH)
        a = a[place[a] + passage <= count[text[a]]]
        parts.append((text[a], place[a], np.ones(len(a), np.int64), starts[a], ends[a + passage - 1], np.full(len(a), passage - k + 1)))
        self.text, self.place, self.kind, at, stop, many = (np.concatenate(x) for x in zip(*parts, strict=True))
        self.at, self.stop = at - offs[self.text], stop - offs[self.text]
        self.lo = begin[:-1][self.text] + self.place
        self.hi = self.lo + many
        self.place = 2 * self.place + self.kind

    def ids(self, docs: np.ndarray) -> np.ndarray:
        if len(self.text) and (docs[self.text].min() < 0 or docs[self.text].max() >= 1 << 37 or self.place.max() >= PLACES):
            raise ValueError("doc_id must lie in 0 to 2^37, and a text can have 2^25 words at most")
        return docs[self.text] * PLACES + self.place


def _sums(values: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    total = np.zeros(len(values) + 1, U)
    np.cumsum(values, out=total[1:])
    return (total[hi] - total[lo]).view(np.int64)


def _least(values: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """The least value of each range; ranges hold something."""
    edges = np.stack([lo, hi], axis=1).ravel()
    return np.minimum.reduceat(np.append(values, values[-1:]), edges)[::2]


def _summaries(k: int, least: int, passage: int, bands: Paths):
    mul, add = _factors(bands.coordinates)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text"):
                u = Units(b, k, least, passage)
                if not len(u.text):
                    continue
                # equal sequences give equal sums; equal sets of unequal sequences meet in the bands
                salt = mix(u.kind.astype(U) + U(77)).view(np.int64)
                one = _sums(mix(u.hashes ^ U(0x5851F42D4C957F2D)), u.lo, u.hi) ^ salt
                two = _sums(mix(u.hashes + U(0x14057B7EF767814F)), u.lo, u.hi)
                is_line = u.kind == 0
                sig = np.zeros((len(u.text), bands.coordinates), np.uint16)
                few = PASSAGE_BANDS * bands.depth
                for c in range(bands.coordinates):
                    turned = (u.hashes ^ add[c]) * mul[c]
                    own = np.flatnonzero(is_line) if c >= few else np.arange(len(u.text))
                    if len(own):
                        sig[own, c] = (mix(_least(turned, u.lo[own], u.hi[own]) + add[c]) & U(0xFFFF)).astype(np.uint16)
                raw = [x.tobytes() if line else x[:few].tobytes() for x, line in zip(sig, is_line.tolist(), strict=True)]
                yield pa.record_batch({"rid": u.ids(np.asarray(col(b, "doc_id"))), "at": u.at.astype(np.int32), "stop": u.stop.astype(np.int32), "n": (u.hi - u.lo).astype(np.int32), "f1": one, "f2": two, "sig": pa.array(raw, pa.binary())})

    return run


def _full(k: int, least: int, passage: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, "text"):
                u = Units(b, k, least, passage)
                ids = u.ids(np.asarray(col(b, "doc_id")))
                own = np.flatnonzero(np.isin(ids, np.asarray(col(b, "wanted").flatten())))
                tokens = [np.unique(u.hashes[u.lo[i] : u.hi[i]]).tobytes() for i in own.tolist()]
                yield pa.record_batch({"rid": ids[own], "tokens": pa.array(tokens, pa.binary())})

    return run


def paragraph_clusters(docs: DataFrame, shingle_words: int = 5, least_words: int = 20, passage_words: int = 32, bands: Paths = BANDS) -> DataFrame:
    """doc_id, first_word, kind, at, stop, cluster, kept for every paragraph that has a near copy.

    Paragraphs are the lines of `least_words` words or more (kind 0) and the passages of `passage_words` words (kind 1);
    shorter stock lines are left to other operators. Sets are distinct five-word shingles (white-space words, A-Z lower-cased). at
    and stop are bytes of the text, a line's with its line break. cluster is the component's first paragraph, packed as
    doc_id * PLACES + 2 * first_word + kind; only that one is kept. Ids lie in 0 to 2^37 (others: ValueError). Texts that
    are null, empty or without such paragraphs give no row; rows that repeat a doc_id must hold equal text.
    """
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("text is not null and doc_id is not null")
    rule = shingle_words, least_words, passage_words
    summary = materialise(src.mapInArrow(_summaries(*rule, bands), "rid long, at int, stop int, n int, f1 long, f2 long, sig binary"))
    classes = materialise(summary.groupBy("f1", "f2", "n").agg(F.min("rid").alias("rid"), F.first("sig").alias("sig"), F.count("*").alias("copies")))
    tidy(classes)

    def full_sets(ids: DataFrame) -> DataFrame:
        wanted = ids.groupBy(F.floor(F.col("rid") / PLACES).alias("doc_id")).agg(F.collect_list("rid").alias("wanted"))
        return src.join(wanted, "doc_id").select("doc_id", "text", "wanted").mapInArrow(_full(*rule), "rid long, tokens binary").dropDuplicates(["rid"])

    # a line with repeated shingles has fewer than n distinct ones, so sizes are left to the confirmation
    linked = link(classes.select("rid", F.lit(1).alias("n"), "sig"), full_sets, bands)
    labelled = classes.join(linked, "rid", "left").where("copies > 1 or component is not null").select("f1", "f2", "n", F.coalesce("component", "rid").alias("cluster"))
    rows = summary.select("rid", "at", "stop", "f1", "f2", "n").join(labelled, ["f1", "f2", "n"])
    place = F.pmod(F.col("rid"), F.lit(PLACES))
    return rows.select(F.floor(F.col("rid") / PLACES).alias("doc_id"), F.floor(place / 2).cast("int").alias("first_word"), F.pmod(place, F.lit(2)).cast("int").alias("kind"), "at", "stop", "cluster", (F.col("rid") == F.col("cluster")).alias("kept"))


def _merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        runs = [[{"at": a, "stop": z} for a, z in joined(own)] for own in col(b, "spans").to_pylist()]
        yield pa.record_batch({"doc_id": col(b, "doc_id"), "removed": pa.array(runs, pa.list_(pa.struct([("at", pa.int32()), ("stop", pa.int32())]))), "clusters": col(b, "clusters")})


def removals(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_removed, removed (array of at, stop: maximal runs of bytes), clusters (rising) for every row of docs; nothing removed: 0 and empty lists."""
    gone = paragraph_clusters(docs, **options).where("not kept").groupBy("doc_id").agg(F.collect_set(F.struct("at", "stop")).alias("spans"), F.array_sort(F.collect_set("cluster")).alias("clusters"))
    gone = gone.mapInArrow(_merged, "doc_id long, removed array<struct<at: int, stop: int>>, clusters array<long>")
    out = docs.select(F.col("doc_id").cast("long").alias("doc_id")).join(gone, "doc_id", "left")
    none, no_cluster = F.array().cast("array<struct<at: int, stop: int>>"), F.array().cast("array<long>")
    return out.select("doc_id", F.coalesce(F.size("removed"), F.lit(0)).cast("long").alias("n_removed"), F.coalesce("removed", none).alias("removed"), F.coalesce("clusters", no_cluster).alias("clusters"))


def _cut(text: str, name: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for own, gone in zip(col(b, text).to_pylist(), col(b, name).to_pylist(), strict=True):
                if gone:
                    raw = own.encode()
                    edges = [0, *(x for g in gone for x in (g["at"], g["stop"])), len(raw)]
                    own = b"".join(raw[edges[i] : edges[i + 1]] for i in range(0, len(edges), 2)).decode()
                out.append(own)
            i = b.schema.get_field_index(text)
            yield b.set_column(i, b.schema.field(i).with_type(pa.string()), pa.array(out, pa.string()))

    return run


def drop_repeated_paragraphs(docs: DataFrame, **options) -> DataFrame:
    """docs with the removed paragraphs cut from text; all rows and columns stay, whatever they are called."""
    name = "gone"
    while name in docs.columns:
        name += "_"
    gone = materialise(removals(docs, **options).where("n_removed > 0").select("doc_id", F.col("removed").alias(name)).dropDuplicates(["doc_id"]))
    wide = docs.join(gone, "doc_id", "left").select(*docs.columns, name)
    return wide.mapInArrow(_cut("text", name), wide.schema).drop(name)
