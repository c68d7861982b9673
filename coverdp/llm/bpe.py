"""Byte-level BPE with two tiers: a minimal perfect hash of the vocabulary, then merges from a heap over linked bytes."""

from __future__ import annotations

import base64
import hashlib
from dataclasses import dataclass
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.llm.textkit import U, col, mix, slices, span_hashes

#: Words of a generation: a worker remembers the present one and the one before, so frequent words stay.
REMEMBER = 150_000


def _hashes(keys: list[bytes]) -> np.ndarray:
    ends = np.cumsum([len(k) for k in keys])
    return span_hashes(np.frombuffer(b"".join(keys), np.uint8), ends - [len(k) for k in keys], ends)


def _slots(h: np.ndarray, shift: np.ndarray | int, n: int) -> np.ndarray:
    return (mix(h ^ (np.asarray(shift).astype(U) * U(0xA0761D6478BD642F))) % U(n)).astype(np.int64)


@dataclass
class PerfectHash:
    """n keys in n slots: buckets of several keys have a displacement, those of one key their slot itself (as -slot - 1)."""

    shift: np.ndarray
    n: int

    @classmethod
    def build(cls, h: np.ndarray) -> PerfectHash:
        """Buckets of one size, from the largest down, try one displacement a round together; of those that clash the first stays."""
        n = len(h)
        buckets = max(1, n // 3)
        bucket = (h % U(buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        begin = np.searchsorted(bucket[order], np.arange(buckets + 1))
        sizes = np.diff(begin)
        shift, free = np.zeros(buckets, np.int64), np.ones(n, bool)
        for size in range(int(sizes.max(initial=0)), 1, -1):
            todo, d = np.flatnonzero(sizes == size), 0
            keys = h[order[begin[todo][:, None] + np.arange(size)]]
            while len(todo):
                d += 1
                slot = np.sort(_slots(keys, d, n), axis=1)
                fits = free[slot].all(axis=1) & (np.diff(slot, axis=1) > 0).all(axis=1)
                taken, first = np.unique(slot[fits].ravel(), return_index=True)
                owner = np.full(n, -1)
                owner[taken] = first // size
                fits[fits] = (owner[slot[fits]] == np.arange(int(fits.sum()))[:, None]).all(axis=1)
                shift[todo[fits]] = d
                free[slot[fits]] = False
                todo, keys = todo[~fits], keys[~fits]
        left = np.flatnonzero(free)
        shift[np.flatnonzero(sizes == 1)] = -left[: int((sizes == 1).sum())] - 1
        return cls(shift, n)

    def slots(self, h: np.ndarray) -> np.ndarray:
        d = self.shift[(h % U(len(self.shift))).astype(np.int64)]
        return np.where(d < 0, -d - 1, _slots(h, np.maximum(d, 0), self.n))


class Codec:
    """Ranks of a tiktoken file: encodes and decodes as that library does without special tokens."""

    def __init__(self, ranks: dict[bytes, int], pattern: str) -> None:
        self.ranks, self.pattern = ranks, pattern
        keys = list(ranks)
        h = _hashes(keys)
        self.table = PerfectHash.build(h)
        self.at_slot = np.zeros(len(keys), np.int64)
        self.at_slot[self.table.slots(h)] = [ranks[k] for k in keys]
        self.bytes_of = {r: k for k, r in ranks.items()}
        self.first_rank = [ranks.get(bytes((a, b)), -1) for a in range(256) for b in range(256)]
        self._forget()

    def _forget(self) -> None:
        self.known: dict[str, str] = {}  # the ids in decimal
        self.before: dict[str, str] = {}
        self.odd: dict[str, bytes] = {}  # what ids decode to, where that isn't the pre-token itself
        self.split = None

    @classmethod
    def load(cls, path: str, pattern: str) -> Codec:
        with open(path, "rb") as lines:
            return cls({base64.b64decode(a): int(b) for a, b in (x.split() for x in lines if x.strip())}, pattern)

    def __getstate__(self):
        return self.__dict__ | {"known": {}, "before": {}, "odd": {}, "split": None}

    def merge(self, word: bytes) -> list[int]:
        """Second tier: the best-ranked adjacent pair first, the leftmost of equals, from a heap with stale entries over linked bytes.

        A part is known by its first byte: `stop` links it to the next one, `back` to the one before, `pair` is the rank
        that it would have with the next (-1: none). Heap entries are rank * n + place.
        """
        get, n = self.ranks.get, len(word)
        stop, back = list(range(1, n + 1)), list(range(-1, n - 1))
        first = self.first_rank
        pair = [first[a << 8 | b] for a, b in zip(word, word[1:])]
        pair.append(-1)
        heap = [r * n + i for i, r in enumerate(pair) if r >= 0]
        heapify(heap)
        while heap:
            rank, i = divmod(heappop(heap), n)
            if pair[i] != rank:
                continue
            j = stop[i]
            k = stop[i] = stop[j]
            pair[i] = pair[j] = -1
            if k < n:
                back[k] = i
                if (r := get(word[i : stop[k]])) is not None:
                    pair[i] = r
                    heappush(heap, r * n + i)
            if (p := back[i]) >= 0:
                pair[p] = r = get(word[p:k], -1)
                if r >= 0:
                    heappush(heap, r * n + p)
        out, i = [], 0
        while i < n:
            out.append(self.ranks[word[i : stop[i]]])
            i = stop[i]
        return out

    def learn(self, tokens: list[str]) -> None:
        """Both tiers for the pre-tokens that this generation hasn't met."""
        known, before = self.known, self.before
        missing = set(tokens).difference(known)
        if not missing:
            return
        if len(known) > REMEMBER:
            self.before, self.known = known, {}
            known, before, missing = self.known, known, set(tokens)
        new = []
        for t in missing:
            if (had := before.get(t)) is None:
                new.append(t)
            else:
                known[t] = had
        if not new:
            return
        raw = [t.encode("utf-8", "surrogatepass") for t in new]
        bytes_of, merge = self.bytes_of, self.merge
        ids = self.at_slot[self.table.slots(_hashes(raw))].tolist()
        for t, b, i in zip(new, raw, ids, strict=True):
            if bytes_of[i] == b:
                known[t] = str(i)
                continue
            own = merge(b)
            known[t] = " ".join(map(str, own))
            if (back := self.decode(own)) != b:
                self.odd[t] = back

    def pretokens(self, text: str) -> list[str]:
        if self.split is None:
            self.split = regex.compile(self.pattern)
        return self.split.findall(text)

    def encode(self, text: str) -> list[int]:
        toks = self.pretokens(text)
        self.learn(toks)
        return [int(i) for t in toks for i in self.known[t].split(" ")]

    def decode(self, ids) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))

    def digest(self, text: str) -> tuple[int, str, str]:
        """(number of ids, SHA-256 of the ids in decimal, SHA-256 of their decoding).

        Every pre-token's ids are decoded when they're learnt; what they gave is joined here.
        """
        toks = self.pretokens(text)
        self.learn(toks)
        written = " ".join(map(self.known.__getitem__, toks))
        if self.odd:
            raw = b"".join(self.odd[t] if t in self.odd else t.encode("utf-8", "surrogatepass") for t in toks)
        else:
            raw = "".join(toks).encode("utf-8", "surrogatepass")
        return written.count(" ") + 1 if toks else 0, hashlib.sha256(written.encode()).hexdigest(), hashlib.sha256(raw).hexdigest()


def _source(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))


def encode(docs: DataFrame, codec: Codec) -> DataFrame:
    """doc_id, ids for every row of docs(doc_id, text). Null and empty texts give no ids."""
    shared = docs.sparkSession.sparkContext.broadcast(codec)  # as large as the vocabulary, whatever the input

    def run(batches):
        for whole in batches:
            for b in slices(whole, "text"):
                yield pa.record_batch({"doc_id": col(b, "doc_id"), "ids": pa.array([shared.value.encode(t) for t in col(b, "text").to_pylist()], pa.list_(pa.int32()))})

    return _source(docs).mapInArrow(run, "doc_id long, ids array<int>")


def decode(encoded: DataFrame, codec: Codec) -> DataFrame:
    """doc_id, payload: the bytes that ids stand for; a null list gives no bytes."""
    shared = encoded.sparkSession.sparkContext.broadcast(codec)

    def run(batches):
        for b in batches:
            yield pa.record_batch({"doc_id": col(b, "doc_id"), "payload": pa.array([shared.value.decode(x or ()) for x in col(b, "ids").to_pylist()], pa.binary())})

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, payload binary")


def round_trip(docs: DataFrame, codec: Codec) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 for every row: encoding and decoding in one pass over the text."""
    shared = docs.sparkSession.sparkContext.broadcast(codec)

    def run(batches):
        for whole in batches:
            for b in slices(whole, "text"):
                found = [shared.value.digest(t) for t in col(b, "text").to_pylist()]
                yield pa.record_batch({"doc_id": col(b, "doc_id"), "n_tokens": pa.array([x[0] for x in found], pa.int64()), "ids_sha256": pa.array([x[1] for x in found], pa.string()), "decoded_sha256": pa.array([x[2] for x in found], pa.string())})

    return _source(docs).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
