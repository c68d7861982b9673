"""Vectorised kernels over the UTF-8 bytes of many texts at once, for Arrow batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
_rng = np.random.RandomState(20240613)
BYTE_CODE = _rng.randint(1, 2**63 - 1, 256, dtype=np.int64).astype(U) * U(2) + U(1)
BASE = U(0x9E3779B97F4A7C15)
BASE_INVERSE = U(pow(int(BASE), -1, 2**64))
STEP = U(0xD6E8FEB86659FD93)
#: White space of the word rule: 0x20 and 0x09 to 0x0D.
WHITE = np.zeros(256, bool)
WHITE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Everything in ASCII that's no letter or digit separates words in the loose rule.
LOOSE = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])
_powers = np.ones(1, U), np.ones(1, U)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _powers
    if len(_powers[0]) < n:
        n = 1 << (n - 1).bit_length()
        up, down = np.full(n, BASE, U), np.full(n, BASE_INVERSE, U)
        up[0] = down[0] = 1
        _powers = np.multiply.accumulate(up), np.multiply.accumulate(down)
    return _powers


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    kind = pa.large_binary()
    column = column.cast(pa.large_string()).cast(kind) if pa.types.is_string(column.type) else column.cast(kind)
    if column.null_count:
        column = column.fill_null(b"")
    n = len(column)
    if not n:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, np.int64, n + 1, column.offset * 8)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[offs[0] : offs[-1]], offs - offs[0]


def slices(batch: pa.RecordBatch, column: str, most: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Pieces of a batch with about `most` bytes of text, one row at least: memory doesn't follow the batch's row count."""
    _, offs = text_bytes(batch.column(batch.schema.get_field_index(column)))
    at, n = 0, batch.num_rows
    while at < n:
        to = max(at + 1, int(np.searchsorted(offs, offs[at] + most, "right")) - 1)
        yield batch.slice(at, to - at)
        at = to


def col(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def words(data: np.ndarray, offs: np.ndarray, white: np.ndarray = WHITE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, first word of each text and the total) of maximal runs without separators, never across texts."""
    n = len(data)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offs), np.int64)
    on = ~white[data]
    edge = np.zeros(n + 1, bool)
    edge[offs] = True
    before = np.empty(n, bool)
    before[0] = False
    before[1:] = on[:-1]
    after = np.empty(n, bool)
    after[-1] = False
    after[:-1] = on[1:]
    starts = np.flatnonzero(on & (~before | edge[:-1]))
    ends = np.flatnonzero(on & (~after | edge[1:])) + 1
    return starts, ends, np.searchsorted(starts, offs)


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, salt: int = 0) -> np.ndarray:
    """64-bit hashes of byte spans, equal spans equal wherever they stand."""
    n = len(data)
    up, down = powers(n + 1)
    total = np.empty(n + 1, U)
    total[0] = 0
    np.cumsum(BYTE_CODE[data] * up[:n], out=total[1:])
    return mix((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(U) * STEP + U(salt))


def shingles(hashes: np.ndarray, first: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of k-word windows and where each text's begin; a text of fewer words, but one at least, gives its whole sequence."""
    counts = np.diff(first)
    m = np.where(counts >= k, counts - k + 1, np.minimum(counts, 1))
    begin = np.concatenate([[0], np.cumsum(m)])
    owner = np.repeat(np.arange(len(m)), m)
    at = first[:-1][owner] + (np.arange(begin[-1]) - begin[:-1][owner])
    out = np.zeros(begin[-1], U)
    for j in range(k):
        live = j < counts[owner]
        step = hashes[np.minimum(at + j, max(len(hashes) - 1, 0))] if len(hashes) else out
        out = np.where(live, out * STEP + step, out)
    return mix(out + np.minimum(counts, k)[owner].astype(U)), begin


def string(values: list[bytes]) -> pa.Array:
    return pa.array(values, pa.binary())
