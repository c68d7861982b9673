"""Exact repeated 50-byte strings across documents, by merging Burrows-Wheeler transforms of shards.

A window of 50 bytes is dealt out by the least hash of the 20-byte grams in it, so equal windows meet in one bucket and
each bucket holds runs of windows. Three steps:

1. every document's least grams go, as compact sorted hashes, to their bucket, which answers with those that two
   documents or more have; what a batch already knows to be shared is answered at once and sent on as one entry;
2. only runs of windows around shared grams travel as bytes, equal runs of a part once. In a bucket, arriving parts
   make shards, each with its own Burrows-Wheeler transform; the transforms are merged by refining the interleave one symbol a
   round, without sorting suffixes anew. A row that parts from all others leaves the refinement; intervals that stay
   together for 50 rounds are the repeated windows, with the least document of each. Runs of a gram that very many
   parts report are dealt out window by window, by the bytes of the window, so that no bucket gathers them;
3. the windows also in a smaller document come back as spans and are joined.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.llm.textkit import BYTE_CODE, U, col, mix, powers, slices, span_hashes, text_bytes
from coverdp.runtime import materialise, release, tidy

GRAM = 20
MULTI = np.int64(-1)
#: A gram that more parts report is hot: its windows are dealt out one by one.
HOT_PARTS = 64
#: Bytes of text a bucket, of strings that are merged at once, of runs that a part puts together before it sends them, and of text that is hashed at once.
BUCKET_BYTES, MERGE_BYTES, PART_BYTES, VIEW_BYTES = 2 << 20, 1 << 18, 4 << 20, 1 << 18
#: Texts pass an exchange in turns of about so many bytes, and buckets in as many, up to MOST_TURNS: what a turn exchanged leaves the disk before the next.
TURN_BYTES, MOST_TURNS = 64 << 20, 4
#: Bytes of strings that share a transform: with many parts each sends a bucket a few strings only, too little for one of their own.
SHARD_BYTES = 1 << 14
#: Grams that a part puts together before it sends them.
PART_KEYS = 1 << 20


def _gram_hashes(data: np.ndarray) -> np.ndarray:
    """The hash of the GRAM bytes from each place; the last places have none."""
    n = len(data)
    if n < GRAM:
        return np.zeros(0, U)
    # Horner's rule for a window of fixed length, by doubling
    level, size = BYTE_CODE[data], 1
    parts = []
    while size <= GRAM:
        parts.append((size, level))
        if size * 2 > GRAM:
            break
        level = level[: len(level) - size] * powers(size + 1)[0][size] + level[size:]
        size *= 2
    out, at, left = None, 0, GRAM
    for size, level in reversed(parts):
        if left >= size:
            piece = level[at : at + n - GRAM + 1]
            out = piece if out is None else out * powers(size + 1)[0][size] + piece
            at += size
            left -= size
    return mix(out)


def _slide(h: np.ndarray, w: int, pick=np.minimum) -> np.ndarray:
    """The least (or greatest) of each w neighbours."""
    size, level = 1, h
    while size * 2 <= w:
        level = pick(level[: len(level) - size], level[size:])
        size *= 2
    return pick(level[: len(h) - w + 1], level[w - size :][: len(h) - w + 1]) if w > size else level


def window_keys(data: np.ndarray, offs: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, first byte, key) of every window of `length` bytes within one text."""
    counts = np.maximum(np.diff(offs) - length + 1, 0)
    text = np.repeat(np.arange(len(counts)), counts)
    if not len(text):
        return text, np.zeros(0, np.int64), np.zeros(0, U)
    at = np.arange(len(text)) + np.repeat(offs[:-1] - (np.cumsum(counts) - counts), counts)
    return text, at, _slide(_gram_hashes(data), length - GRAM + 1)[at]


def _views(data: np.ndarray, offs: np.ndarray, length: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(rows, first byte of each in its text, bytes, offsets) of about VIEW_BYTES; longer texts come in parts that share no window and miss none."""
    i, n = 0, len(offs) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offs, offs[i] + VIEW_BYTES, "right")) - 1)
        if offs[j] - offs[i] <= VIEW_BYTES:
            yield np.arange(i, j), np.zeros(j - i, np.int64), data[offs[i] : offs[j]], offs[i : j + 1] - offs[i]
        else:
            for a in range(int(offs[i]), int(offs[j]) - length + 1, VIEW_BYTES):
                z = min(a + VIEW_BYTES + length - 1, int(offs[j]))
                yield np.array([i]), np.array([a - offs[i]]), data[a:z], np.array([0, z - a])
        i = j


def _pack(h: np.ndarray) -> bytes:
    """Sorted hashes as differences in byte planes."""
    d = np.diff(h, prepend=U(0)).view(np.uint8).reshape(-1, 8)
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(d.T).tobytes())


def _unpack(raw: bytes) -> np.ndarray:
    d = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(d.T).view(U).ravel(), dtype=U)


def _press(a: np.ndarray) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(a).tobytes())


def _release(raw: bytes, kind) -> np.ndarray:
    return np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), kind)


def _grams(buckets: int, length: int):
    """For each bucket the keys of a part's documents; keys that two documents of the part share are answered here."""

    def packed(keys: list[np.ndarray], owner: list[np.ndarray]) -> pa.RecordBatch:
        key, doc = np.concatenate(keys), np.concatenate(owner)
        order = np.lexsort((doc, key))
        key, doc = key[order], doc[order]
        once = np.ones(len(key), bool)
        once[1:] = (key[1:] != key[:-1]) | (doc[1:] != doc[:-1])
        key, doc = key[once], doc[once]
        head = np.ones(len(key), bool)
        head[1:] = key[1:] != key[:-1]
        group = np.cumsum(head) - 1
        shared = np.bincount(group)[group] > 1
        sent = np.where(shared, MULTI, doc)[head]
        k = key[head]
        rows = [], [], [], []
        bucket = (k % U(buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        for part in np.split(order, np.flatnonzero(np.diff(bucket[order])) + 1):
            rows[0].append(int(bucket[part[0]])), rows[1].append(False), rows[2].append(_pack(k[part])), rows[3].append(_press(sent[part]))
        if shared.any():
            # answered already; dealt out evenly for passing on
            sk, sd = key[shared], doc[shared]
            home = (mix(sd.view(U)) % U(min(buckets, 16))).astype(np.int64)
            for x in np.unique(home):
                own = home == x
                rows[0].append(int(mix(np.array([sd[own][0]]).view(U))[0] % U(buckets))), rows[1].append(True), rows[2].append(_pack(sk[own])), rows[3].append(_press(sd[own]))
        return pa.record_batch({"bucket": pa.array(rows[0], pa.int32()), "known": pa.array(rows[1], pa.bool_()), "keys": pa.array(rows[2], pa.binary()), "docs": pa.array(rows[3], pa.binary())})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            keys, owner, held = [], [], 0
            for b in slices(whole, "text"):
                ids = np.asarray(col(b, "doc_id"))
                for rows, _, data, offs in _views(*text_bytes(col(b, "text")), length):
                    text, at, key = window_keys(data, offs, length)
                    if not len(at):
                        continue
                    new = np.ones(len(at), bool)
                    new[1:] = (key[1:] != key[:-1]) | (text[1:] != text[:-1])
                    keys.append(key[new]), owner.append(ids[rows[text[new]]])
                    held += len(keys[-1])
                if held > PART_KEYS:
                    yield packed(keys, owner)
                    keys, owner, held = [], [], 0
            if keys:
                yield packed(keys, owner)

    return run


def _shared(hot_parts: int):
    """(doc_id, key): of a bucket's keys those with two documents or more; a row without doc_id marks a hot key."""

    def run(table: pa.Table) -> pa.Table:
        key, doc, know_k, know_d = [], [], [], []
        for known, k, d in zip(table["known"].to_pylist(), table["keys"].to_pylist(), table["docs"].to_pylist(), strict=True):
            (know_k if known else key).append(_unpack(k)), (know_d if known else doc).append(_release(d, np.int64))
        out_k, out_d, hot = know_k, know_d, np.zeros(0, U)
        if key:
            k, d = np.concatenate(key), np.concatenate(doc)
            order = np.argsort(k, kind="stable")
            k, d = k[order], d[order]
            head = np.ones(len(k), bool)
            head[1:] = k[1:] != k[:-1]
            group = np.cumsum(head) - 1
            repeated = (np.bincount(group) > 1) | np.bitwise_or.reduceat(d == MULTI, np.flatnonzero(head))
            keep = repeated[group] & (d != MULTI)
            hot = k[head][np.bincount(group) > hot_parts]
            out_k, out_d = [*know_k, k[keep]], [*know_d, d[keep]]
        k, d = (np.concatenate(x) if x else np.zeros(0, t) for x, t in ((out_k, U), (out_d, np.int64)))
        docs = pa.array(np.concatenate([d, np.zeros(len(hot), np.int64)]), mask=np.repeat([False, True], [len(d), len(hot)]))
        return pa.table({"doc_id": docs, "key": np.concatenate([k, hot]).view(np.int64)})

    return run


def _squeeze(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts as compressed bytes, for the exchanges that they pass."""
    press = zstandard.ZstdCompressor(level=1)
    for b in batches:
        data, offs = text_bytes(col(b, "text"))
        own = data.tobytes()
        yield pa.record_batch({"doc_id": col(b, "doc_id"), "z": pa.array([press.compress(own[offs[i] : offs[i + 1]]) for i in range(b.num_rows)], pa.binary())})


def _take(data: np.ndarray, lo: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The bytes of spans, one after another."""
    begin = np.cumsum(size) - size
    return data[np.repeat(lo - begin, size) + np.arange(int(size.sum()))]


def _strings(raw: np.ndarray, size: np.ndarray) -> pa.Array:
    offs = np.concatenate([[0], np.cumsum(size)]).astype(np.int64)
    return pa.Array.from_buffers(pa.large_binary(), len(size), [None, pa.py_buffer(offs), pa.py_buffer(np.ascontiguousarray(raw))])


def _marked(lists: pa.Array) -> np.ndarray:
    """Sorted hashes of (row, key) of a column of lists of keys."""
    n = np.asarray(lists.value_lengths().fill_null(0))
    return np.unique(_mark(np.repeat(np.arange(len(n)), n), np.asarray(lists.flatten()).view(U)))


def _mark(row: np.ndarray, key: np.ndarray) -> np.ndarray:
    return mix(key ^ mix(row.astype(U) + U(1)))


def _among(sorted_: np.ndarray, x: np.ndarray) -> np.ndarray:
    if not len(sorted_):
        return np.zeros(len(x), bool)
    return sorted_[np.minimum(np.searchsorted(sorted_, x), len(sorted_) - 1)] == x


def _runs(buckets: int, length: int, longest: int):
    """Runs of windows with one shared key, as bytes; in a part equal runs are sent once, with the least document.

    Of a part's equal runs the other documents lose all windows at once (bucket -1 rows are spans already known).
    """

    def found(b: pa.RecordBatch) -> Iterator[tuple[np.ndarray, ...]]:
        """(documents, places, sizes, buckets, bytes) of the runs of a few rows."""
        open_ = zstandard.ZstdDecompressor()
        raw = [open_.decompress(z.as_buffer()) for z in col(b, "z")]
        ids, keys, hot = np.asarray(col(b, "doc_id")), _marked(col(b, "keys")), _marked(col(b, "hot"))
        for rows, shift, data, offs in _views(np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)]), length):
            text, at, key = window_keys(data, offs, length)
            if not len(at):
                continue
            head = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (text[1:] != text[:-1])]))
            n = np.diff(np.append(head, len(at)))
            mark = _mark(rows[text[head]], key[head])
            wanted = _among(keys, mark)
            head, n, single = head[wanted], n[wanted], _among(hot, mark[wanted])
            if not len(head):
                continue
            step = np.where(single, 1, longest)
            many = -(-n // step)
            nth = np.arange(int(many.sum())) - np.repeat(np.cumsum(many) - many, many)
            head, n, step, single = (np.repeat(x, many) for x in (head, n, step, single))
            lo = at[head] + nth * step
            size = np.minimum(step, n - nth * step) + length - 1
            bucket = (np.where(single, span_hashes(data, lo, lo + size), key[head]) % U(buckets)).astype(np.int64)
            yield ids[rows[text[head]]], lo - offs[text[head]] + shift[text[head]], size, bucket, _take(data, lo, size)

    def packed(parts: list[tuple[np.ndarray, ...]]) -> Iterator[pa.RecordBatch]:
        doc, place, size, bucket, raw = (np.concatenate(x) for x in zip(*parts, strict=True))
        code = np.asarray(_strings(raw, size).dictionary_encode().indices)
        least = np.full(int(code.max()) + 1, np.iinfo(np.int64).max)
        np.minimum.at(least, code, doc)
        sent = doc == least[code]
        if not sent.all():
            own = np.flatnonzero(~sent)
            yield pa.record_batch({"bucket": pa.array([-1], pa.int32()), "docs": [_press(doc[own])], "at": [_press(place[own])], "sizes": [_press(size[own].astype(np.int32))], "raw": [b""]}, schema=_RUNS)
        begin = np.cumsum(size) - size
        order = np.flatnonzero(sent)
        order = order[np.argsort(bucket[order], kind="stable")]
        rows: dict[str, list] = {"bucket": [], "docs": [], "at": [], "sizes": [], "raw": []}
        for own in np.split(order, np.flatnonzero(np.diff(bucket[order])) + 1):
            rows["bucket"].append(int(bucket[own[0]])), rows["docs"].append(_press(doc[own])), rows["at"].append(_press(place[own]))
            rows["sizes"].append(_press(size[own].astype(np.int32))), rows["raw"].append(_press(_take(raw, begin[own], size[own])))
        yield pa.record_batch(rows, schema=_RUNS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, held = [], 0
        for whole in batches:
            for at in range(0, whole.num_rows, 64):
                for part in found(whole.slice(at, 64)):
                    parts.append(part)
                    held += len(part[-1])
                    if held > PART_BYTES:
                        yield from packed(parts)
                        parts, held = [], 0
        if parts:
            yield from packed(parts)

    return run


_RUNS = pa.schema([("bucket", pa.int32()), ("docs", pa.binary()), ("at", pa.binary()), ("sizes", pa.binary()), ("raw", pa.binary())])


def shard_transform(strings: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(transform, string, offset) of all suffixes in order. Bytes count one up; 0 ends a string; ends rank by string."""
    n, width = len(strings), max(map(len, strings)) + 1
    sizes = np.array([len(s) for s in strings])
    grid = np.zeros((n, 2 * width), np.uint8)
    for size in np.unique(sizes):
        own = np.flatnonzero(sizes == size)
        grid[own, :size] = np.frombuffer(b"".join(strings[i] for i in own), np.uint8).reshape(-1, size) + 1
    string = np.repeat(np.arange(n), sizes + 1)
    offset = np.arange(len(string)) - np.repeat(np.cumsum(sizes + 1) - sizes - 1, sizes + 1)
    windows = np.lib.stride_tricks.sliding_window_view(grid, width, axis=1)
    order = np.argsort(windows[string, offset].reshape(len(string), width).copy().view(f"S{width}").ravel(), kind="stable")
    # stable: equal suffixes, which end together, stay in the order of their strings
    string, offset = string[order], offset[order]
    return np.where(offset > 0, grid[string, np.maximum(offset - 1, 0)], 0).astype(np.uint8), string, offset


def merge_transforms(transforms: list[np.ndarray], ends: list[int], rounds: int) -> tuple[np.ndarray, np.ndarray]:
    """(rows, interval of each) of the merged transform: rows, numbered shard after shard, whose first `rounds` symbols another has too.

    The interleave starts as the shards one after another, in one interval. Each round sends every row to the place of
    the suffix one symbol longer, stably, so after j rounds rows stand in the order of their first j symbols and
    an interval holds those that agree in them. A row alone in its interval stays alone however far it is extended,
    and leaves; so does a string's end, which equals none. ends: strings of each shard.
    """
    sizes = np.array([len(t) for t in transforms])
    start = np.cumsum(sizes) - sizes
    longer = np.concatenate([np.empty(0, np.int64), *(_extend(t) + s for t, s in zip(transforms, start, strict=True))])
    symbols = np.concatenate(transforms)
    number = np.int32 if len(symbols) < 1 << 31 else np.int64
    longer, rows = longer.astype(number), np.arange(len(symbols), dtype=number)
    interval = np.zeros(len(rows), number)
    for _ in range(rounds):
        c = symbols[rows]
        live = np.flatnonzero(c)
        order = live[np.argsort(c[live], kind="stable")]
        c, rows, interval = c[order], longer[rows[order]], interval[order]
        if not len(rows):
            break
        edge = np.concatenate([[True], (c[1:] != c[:-1]) | (interval[1:] != interval[:-1])])
        alone = edge & np.append(edge[1:], True)
        rows, interval = rows[~alone], np.cumsum(edge, dtype=number)[~alone]
    return rows, interval


def _extend(transform: np.ndarray) -> np.ndarray:
    """For each row of a transform the row of the suffix one symbol longer."""
    out = np.empty(len(transform), np.int64)
    out[np.argsort(transform, kind="stable")] = np.arange(len(transform))
    return out


def least_documents(shards: list[list[bytes]], docs: list[np.ndarray], length: int) -> list[np.ndarray]:
    """For each string, shard after shard, the least document of each of its windows of `length` bytes. docs: of the strings of each shard."""
    built = [shard_transform(strings) for strings in shards]
    rows, interval = merge_transforms([b[0] for b in built], [len(s) for s in shards], length)
    base = np.cumsum([0, *(len(s) for s in shards)])
    string = np.concatenate([b[1] + n for b, n in zip(built, base, strict=False)])
    offset = np.concatenate([b[2] for b in built])
    doc = np.concatenate(docs)
    windows = np.array([len(x) - length + 1 for s in shards for x in s], np.int64)
    begin = np.cumsum(windows) - windows
    out = np.repeat(doc, windows)
    if len(rows):
        heads = np.flatnonzero(np.concatenate([[True], interval[1:] != interval[:-1]]))
        least = np.minimum.reduceat(doc[string[rows]], heads)
        out[begin[string[rows]] + offset[rows]] = np.repeat(least, np.diff(np.append(heads, len(rows))))
    return np.split(out, begin[1:])


def _solve(names: pa.Array, shard: np.ndarray, doc: np.ndarray, key: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """(where each string's windows begin, their least documents) of distinct strings: sets of whole keys of about MERGE_BYTES are merged, from shards of about SHARD_BYTES."""
    size = np.asarray(pa.compute.binary_length(names)).astype(np.int64)
    windows = size - length + 1
    begin = np.cumsum(windows) - windows
    least = np.repeat(doc, windows)
    order = np.lexsort((shard, key))
    head = np.flatnonzero(np.concatenate([[True], key[order][1:] != key[order][:-1]]))
    many = np.diff(np.append(head, len(order)))
    load = np.add.reduceat(size[order], head)
    # a string alone with its key has nothing to merge
    group = np.repeat(np.where(many > 1, np.cumsum(np.where(many > 1, load, 0)) // MERGE_BYTES, -1), many)
    order, group = order[group >= 0], group[group >= 0]
    for own in np.split(order, np.flatnonzero(np.diff(group)) + 1) if len(order) else []:
        own = own[np.argsort(shard[own], kind="stable")]
        parts = np.split(own, np.flatnonzero(np.diff((np.cumsum(size[own]) - size[own]) // SHARD_BYTES)) + 1)
        shards = [names.take(pa.array(x)).to_pylist() for x in parts]
        for i, found in zip(own.tolist(), least_documents(shards, [doc[x] for x in parts], length), strict=True):
            least[begin[i] : begin[i] + windows[i]] = found
    return begin, least


def _resolve(length: int):
    """Of a bucket's runs the spans of windows that a smaller document has too."""

    def run(table: pa.Table) -> pa.Table:
        parts = [[_release(x, kind) for x in table[name].to_pylist()] for name, kind in (("docs", np.int64), ("at", np.int64), ("sizes", np.int32), ("raw", np.uint8))]
        doc, at, size, raw = (np.concatenate([np.zeros(0, np.int64), *x] if i < 3 else [np.zeros(0, np.uint8), *x]) for i, x in enumerate(parts))
        if not len(doc):
            return pa.table({x: pa.array([], pa.int64()) for x in ("doc_id", "at", "stop")})
        part = np.repeat(np.arange(len(parts[0])), [len(x) for x in parts[0]])
        coded = _strings(raw, size).dictionary_encode()
        code, names = np.asarray(coded.indices), coded.dictionary
        n = len(names)
        least, shard = np.full(n, np.iinfo(np.int64).max), np.full(n, len(parts[0]))
        np.minimum.at(least, code, doc)
        np.minimum.at(shard, code, part)
        data, offs = text_bytes(names)
        text, _, keys = window_keys(data, offs, length)
        key = keys[np.searchsorted(text, np.arange(n))]
        begin, found = _solve(names, shard, least, key, length)
        windows = size - length + 1
        flat = np.repeat(begin[code] - (np.cumsum(windows) - windows), windows) + np.arange(int(windows.sum()))
        owner = np.repeat(np.arange(len(doc)), windows)
        hit = np.flatnonzero(found[flat] < doc[owner])
        if not len(hit):
            return pa.table({x: pa.array([], pa.int64()) for x in ("doc_id", "at", "stop")})
        offset = (np.arange(len(flat)) - np.repeat(np.cumsum(windows) - windows, windows))[hit]
        owner = owner[hit]
        edge = np.concatenate([[True], (np.diff(hit) > 1) | (owner[1:] != owner[:-1])])
        last = np.append(np.flatnonzero(edge)[1:] - 1, len(hit) - 1)
        own = owner[edge]
        return pa.table({"doc_id": doc[own], "at": at[own] + offset[edge], "stop": at[own] + offset[last] + length})

    return run


def _known(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for docs, at, sizes in zip(col(b, "docs").to_pylist(), col(b, "at").to_pylist(), col(b, "sizes").to_pylist(), strict=True):
            a, n = _release(at, np.int64), _release(sizes, np.int32)
            yield pa.record_batch({"doc_id": _release(docs, np.int64), "at": a, "stop": a + n})


def _source(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).where("doc_id is not null")


def repeated_spans(docs: DataFrame, length: int = 50, hot_parts: int = HOT_PARTS) -> DataFrame:
    """doc_id, spans (at, stop): the bytes covered by a string of `length` bytes that also starts in a smaller doc_id.

    Spans of a document may touch or overlap. Null and empty texts have none.
    """
    src = _source(docs)
    size = src.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = min(max(16, size // BUCKET_BYTES), (1 << 31) - 1)
    longest = length - GRAM + 1
    sent = src.mapInArrow(_grams(buckets, length), "bucket int, known boolean, keys binary, docs binary")
    shared = materialise(sent.groupBy("bucket").applyInArrow(_shared(hot_parts), "doc_id long, key long"))
    tidy(shared)
    hot = materialise(shared.where("doc_id is null").select("key", F.lit(True).alias("is_hot")))
    marked = shared.where("doc_id is not null").join(hot, "key", "left")
    answers = marked.groupBy("doc_id").agg(F.collect_list("key").alias("keys"), F.collect_list(F.when(F.col("is_hot"), F.col("key"))).alias("hot"))
    turns = max(1, min(MOST_TURNS, -(-size // TURN_BYTES)))
    cut = []
    for i in range(turns):
        own = F.pmod(F.xxhash64("doc_id"), F.lit(turns)) == i
        pressed = src.where(own).mapInArrow(_squeeze, "doc_id long, z binary")
        cut.append(materialise(pressed.join(answers.where(own), "doc_id").select("doc_id", "z", "keys", "hot").mapInArrow(_runs(buckets, length, longest), "bucket int, docs binary, at binary, sizes binary, raw binary")))
        tidy(shared)
    release(shared, hot)
    runs = reduce(DataFrame.union, cut)
    found = [materialise(runs.where("bucket < 0").mapInArrow(_known, "doc_id long, at long, stop long"))]
    for i in range(turns):
        own = runs.where((F.col("bucket") >= 0) & (F.col("bucket") % turns == i))
        found.append(materialise(own.groupBy("bucket").applyInArrow(_resolve(length), "doc_id long, at long, stop long")))
        tidy(runs)
    release(*cut)
    out = materialise(reduce(DataFrame.union, found).groupBy("doc_id").agg(F.collect_set(F.struct("at", "stop")).alias("spans")))
    release(*found)
    return out


def joined(spans: list[dict]) -> list[tuple[int, int]]:
    """Maximal runs of covered bytes."""
    out: list[tuple[int, int]] = []
    for a, z in sorted((s["at"], s["stop"]) for s in spans):
        if out and a <= out[-1][1]:
            out[-1] = out[-1][0], max(z, out[-1][1])
        else:
            out.append((a, z))
    return out


def remove_repeats(docs: DataFrame, length: int = 50, hot_parts: int = HOT_PARTS) -> DataFrame:
    """doc_id, n_bytes, n_removed, removed (array of at, stop), kept (bytes) for every row of docs with a doc_id.

    What is kept is bytes: a span may begin or end within a character. Repeats within a document alone stay. Rows
    that repeat a doc_id are one document: the spans of each are cut from all of them, as far as a text reaches.
    """
    spans = repeated_spans(docs, length, hot_parts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_ = zstandard.ZstdDecompressor()
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                size, gone, removed, kept = [], [], [], []
                for z, own in zip(col(part, "z").to_pylist(), col(part, "spans").to_pylist(), strict=True):
                    raw = open_.decompress(z)
                    runs = [(a, min(s, len(raw))) for a, s in joined(own or []) if a < len(raw)]
                    edges = [0, *(x for r in runs for x in r), len(raw)]
                    kept.append(b"".join(raw[edges[i] : edges[i + 1]] for i in range(0, len(edges), 2)))
                    size.append(len(raw)), gone.append(len(raw) - len(kept[-1])), removed.append([{"at": a, "stop": s} for a, s in runs])
                yield pa.record_batch({"doc_id": col(part, "doc_id"), "n_bytes": pa.array(size, pa.int64()), "n_removed": pa.array(gone, pa.int64()), "removed": pa.array(removed, pa.list_(pa.struct([("at", pa.int64()), ("stop", pa.int64())]))), "kept": pa.array(kept, pa.binary())})

    pressed = _source(docs).mapInArrow(_squeeze, "doc_id long, z binary")
    return pressed.join(spans, "doc_id", "left").mapInArrow(run, "doc_id long, n_bytes long, n_removed long, removed array<struct<at: long, stop: long>>, kept binary")
