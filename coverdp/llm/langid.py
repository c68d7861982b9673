"""Language identification by hyperdimensional profiles of letter trigrams."""

from __future__ import annotations

from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.llm.textkit import U, col, mix, slices

#: Letters fall into 64 classes: 0 a gap, 1-26 a to z, the rest by code point.
CLASSES = 64


#: Documents and distinct trigrams that are bundled at once.
DOCS, GRAMS = 128, 8192


@cache
def _letter_classes() -> np.ndarray:
    out = np.zeros(0x110000, np.uint8)
    letters = np.array([cp for cp in range(0x40000) if chr(cp).isalpha()])  # no letters stand beyond
    out[letters] = U(27) + mix(letters.astype(U)) % U(CLASSES - 27)
    out[97:123] = np.arange(1, 27)
    return out


@cache
def _places(dim: int, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One letter vector a class, as it's bound in each place: the first twice permuted, the second once, the third not."""
    letters = np.random.RandomState(seed).choice(np.array([-1, 1], np.int8), (CLASSES, dim))
    return np.roll(letters, 2, axis=1), np.roll(letters, 1, axis=1), letters


def _bundles(texts: list[str | None], dim: int, seed: int) -> np.ndarray:
    """A row for each text: the sum of its trigrams' vectors, zeros where it has no letters."""
    out = np.zeros((len(texts), dim), np.float32)
    lower = [(t or "").lower() for t in texts]
    cls = _letter_classes()[np.frombuffer(" ".join(["", *lower, ""]).encode("utf-32-le", "replace"), np.uint32)]
    doc = np.repeat(np.arange(-1, len(texts), dtype=np.int32), [1, *(len(t) + 1 for t in lower)])
    keep = np.ones(len(cls), bool)
    keep[1:] = (cls[1:] > 0) | (cls[:-1] > 0)
    cls, doc = cls[keep].astype(np.int32), doc[keep]
    if len(cls) < 3:
        return out
    gram = (cls[:-2] * CLASSES + cls[1:-1]) * CLASSES + cls[2:]
    # a gap in the middle may stand between two texts
    own = (cls[1:-1] > 0) | (doc[:-2] == doc[2:])
    gram, doc = gram[own], np.where(cls[1:-1] > 0, doc[1:-1], doc[:-2])[own]
    there = np.zeros(CLASSES**3, bool)
    there[gram] = True
    names = np.flatnonzero(there)
    rank = np.cumsum(there, dtype=np.int32)[gram] - 1
    first, second, third = _places(dim, seed)
    for at in range(0, len(names), GRAMS):
        part = names[at : at + GRAMS]
        r, d = rank - at, doc
        if len(names) > GRAMS:
            near = (r >= 0) & (r < GRAMS)
            r, d = r[near], d[near]
        counts = np.bincount(d.astype(np.int64) * len(part) + r, minlength=len(texts) * len(part)).reshape(len(texts), -1)
        bound = first[part // CLASSES**2] * second[part // CLASSES % CLASSES] * third[part % CLASSES]
        out += counts.astype(np.float32) @ bound.astype(np.float32)
    return out


def _profiles(batch: pa.RecordBatch, dim: int, seed: int) -> np.ndarray:
    """Unit vectors of a batch's rows, zeros for texts without letters."""
    texts = col(batch, "text").to_pylist()
    found = np.concatenate([_bundles(texts[i : i + DOCS], dim, seed) for i in range(0, len(texts), DOCS)])
    return found / np.maximum(np.linalg.norm(found, axis=1, keepdims=True), 1e-9)


def _has_letters(text: str | None) -> bool:
    return any(map(str.isalpha, text or ""))


def train(docs: DataFrame, dim: int = 512, seed: int = 7) -> dict[str, np.ndarray]:
    """A unit prototype for each non-null lang of docs(text, lang): the bundle of its unit document vectors.

    Every row counts, none is sampled. Only one vector a language reaches the driver. An empty table gives no
    prototype.
    """

    def run(batches):
        for whole in batches:
            total: dict[str, np.ndarray] = {}
            for b in slices(whole, "text"):
                langs, vectors = np.array(col(b, "lang").to_pylist(), object), _profiles(b, dim, seed)
                for lang in set(langs.tolist()):
                    total[lang] = total.get(lang, np.zeros(dim)) + vectors[langs == lang].sum(axis=0, dtype=np.float64)
            for lang, v in total.items():
                yield pa.record_batch({"lang": pa.array([lang] * dim), "pos": np.arange(dim, dtype=np.int32), "value": v})

    parts = docs.where("lang is not null and text is not null").select("text", "lang").mapInArrow(run, "lang string, pos int, value double")
    summed = parts.groupBy("lang", "pos").agg(F.sum("value").alias("value"))
    out: dict[str, np.ndarray] = {}
    for lang, v in summed.groupBy("lang").agg(F.array_sort(F.collect_list(F.struct("pos", "value"))).alias("v")).select("lang", "v.value").orderBy("lang").collect():
        vec = np.array(v)
        out[lang] = vec / max(np.linalg.norm(vec), 1e-9)
    return out


def identify(docs: DataFrame, prototypes: dict[str, np.ndarray], dim: int = 512, seed: int = 7) -> DataFrame:
    """doc_id, lang_pred, score for every row: the prototype of the greatest cosine, cut to [0, 1].

    Null texts and texts without letters give `und` and 0, as does a model without prototypes. Ties go to the first
    language by name.
    """
    names = sorted(prototypes)
    matrix = np.array([prototypes[x] for x in names]) if names else np.zeros((0, dim))

    def run(batches):
        for whole in batches:
            for b in slices(whole, "text"):
                langs, scores = ["und"] * b.num_rows, [0.0] * b.num_rows
                cosines = _profiles(b, dim, seed) @ matrix.T
                for i, text in enumerate(col(b, "text").to_pylist() if names else []):
                    if _has_letters(text):
                        best = int(cosines[i].argmax())
                        langs[i], scores[i] = names[best], float(min(1.0, max(0.0, cosines[i, best])))
                yield pa.record_batch({"doc_id": col(b, "doc_id"), "lang_pred": pa.array(langs, pa.string()), "score": pa.array(scores, pa.float64())})

    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return src.mapInArrow(run, "doc_id long, lang_pred string, score double")
