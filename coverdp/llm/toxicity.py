"""Toxicity by two class-conditional Kneser-Ney models over letters, which share their backoff counts.

Letters rather than words: abusive stems occur within compounds, and most words of a large corpus are too rare to
count. Text is folded to 64 symbols (a gap, a to z, digits, 36 classes of other bytes). Orders 6 to 4 are counted by
class; below, rare expressions fall back on what all documents share.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.llm.textkit import LOOSE, LOWER, col, slices, text_bytes
from coverdp.runtime import materialise

ORDER, SHARED, BITS = 6, 4, 6
SYMBOL = np.array([0 if LOOSE[b] else b - 96 if 97 <= b <= 122 else 27 if 48 <= b <= 57 else 28 + b % 36 for b in LOWER], np.int64)


@dataclass
class Model:
    """For each order from 6 to 4 the sorted n-grams that have an entry, and their log-likelihood ratios; the calibration."""

    grams: list[np.ndarray]
    ratios: list[np.ndarray]
    weights: np.ndarray | None = None


def _symbols(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """(symbols of all texts, where each begins): gaps are single, and each text begins and ends with one."""
    data, offs = text_bytes(col(batch, "text"))
    n = len(offs) - 1
    # one more gap before each text, so that none runs into the next
    out = np.zeros(len(data) + n, np.int64)
    owner = np.repeat(np.arange(n), np.diff(offs))
    out[np.arange(len(data)) + owner + 1] = SYMBOL[data]
    begin = offs[:-1] + np.arange(n)
    keep = np.ones(len(out), bool)
    keep[1:] = (out[1:] > 0) | (out[:-1] > 0)
    keep[begin] = True
    place = np.concatenate([[0], np.cumsum(keep)])
    return out[keep], place[np.append(begin, len(out))]


def _codes(symbols: np.ndarray, first: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """(text, code) of each n-gram; a text's first symbols are extended to the left by gaps."""
    code = symbols.copy()
    place = np.arange(len(symbols)) - np.repeat(first[:-1], np.diff(first))
    for j in range(1, order):
        before = np.zeros_like(symbols)
        before[j:] = symbols[:-j] if j else symbols
        code |= np.where(place >= j, before, 0) << (BITS * j)
    return np.repeat(np.arange(len(first) - 1), np.diff(first)), code


def _find(sorted_keys: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Places in sorted_keys, -1 where absent."""
    if not len(sorted_keys):
        return np.full(len(keys), -1)
    at = np.minimum(np.searchsorted(sorted_keys, keys), len(sorted_keys) - 1)
    return np.where(sorted_keys[at] == keys, at, -1)


def _class_counts(batches):
    """Documents of each n-gram by class, summed a piece."""
    for whole in batches:
        for b in slices(whole, "text"):
            toxic = np.asarray(col(b, "toxic"))
            text, code = _codes(*_symbols(b), ORDER)
            for c in (0, 1):
                own = toxic[text] == c
                pairs = np.unique(np.stack([code[own], text[own]]), axis=1) if own.any() else np.zeros((2, 0), np.int64)
                grams, n = np.unique(pairs[0], return_counts=True)
                yield pa.record_batch({"cls": np.full(len(grams), c, np.int32), "gram": grams, "n": n.astype(np.int64)})


def _corpus_counts(batches):
    """Counts of the shared order's n-grams, summed a task."""
    grams, counts = [], []

    def merged():
        g, inverse = np.unique(np.concatenate(grams), return_inverse=True)
        return g, np.bincount(inverse, np.concatenate(counts)).astype(np.int64)

    for whole in batches:
        for b in slices(whole, "text"):
            g, n = np.unique(_codes(*_symbols(b), SHARED)[1].astype(np.int32), return_counts=True)
            grams.append(g), counts.append(n)
            if len(grams) > 32:
                g, n = merged()
                grams, counts = [g], [n]
    if grams:
        g, n = merged()
        yield pa.record_batch({"gram": g.astype(np.int32), "n": n})


def _interpolate(grams: np.ndarray, counts: np.ndarray, lower: np.ndarray, discount: float) -> np.ndarray:
    """P(last symbol | the ones before) of each sorted gram: its discounted share plus what is freed times `lower`."""
    context, group = np.unique(grams >> BITS, return_inverse=True)
    total = np.bincount(group, counts, len(context))[group]
    kinds = np.bincount(group, counts > 0, len(context))[group]
    some = np.maximum(total, 1e-9)
    return np.where(total > 0, np.maximum(counts - discount, 0) / some + np.minimum(1, discount * kinds / some) * lower, lower)


def _continuations(grams: np.ndarray, counts: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """The n-grams one shorter, and in how many of these grams each stands at the end."""
    shorter, group = np.unique(grams & ((1 << BITS * (order - 1)) - 1), return_inverse=True)
    return shorter, np.bincount(group, counts > 0, len(shorter))


def shared_probabilities(grams: np.ndarray, counts: np.ndarray, discount: float) -> np.ndarray:
    """Of the corpus' n-grams of the shared order, by Kneser-Ney down to a uniform symbol."""
    levels = [(grams, counts)]
    for order in range(SHARED, 1, -1):
        levels.append(_continuations(*levels[-1], order))
    p = np.full(len(levels[-1][0]), 2.0**-BITS)
    last = levels[-1][1]
    p = np.maximum(last - discount, 0) / max(last.sum(), 1) + discount * len(last) / max(last.sum(), 1) * p
    for (longer, n), (shorter, _), order in zip(levels[-2::-1], levels[:0:-1], range(2, SHARED + 1), strict=True):
        p = _interpolate(longer, n, p[_find(shorter, longer & ((1 << BITS * (order - 1)) - 1))], discount)
    return p


def fit_ratios(grams: np.ndarray, counts: tuple[np.ndarray, np.ndarray], shared: tuple[np.ndarray, np.ndarray], discount: float) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """n-grams and log-likelihood ratios for the orders 6, 5 and 4. shared: the corpus' n-grams and their probabilities."""
    keys, logs = [grams], []
    for order in range(ORDER, SHARED, -1):
        keys.append(_continuations(keys[-1], np.ones(len(keys[-1])), order)[0])
    at = _find(shared[0], keys[-1])
    base = np.where(at >= 0, shared[1][at] if len(shared[1]) else 0, 2.0 ** (-2 * BITS))
    for c in (0, 1):
        own = [counts[c]]
        for order, longer, shorter in zip(range(ORDER, SHARED, -1), keys[:-1], keys[1:], strict=True):
            found, n = _continuations(longer[own[-1] > 0], own[-1][own[-1] > 0], order)
            all_ = np.zeros(len(shorter))
            all_[_find(shorter, found)] = n
            own.append(all_)
        p, ps = base, []
        for k in range(len(keys) - 1, -1, -1):
            if ps:
                p = p[_find(keys[k + 1], keys[k] & ((1 << BITS * (ORDER - k - 1)) - 1))]
            p = _interpolate(keys[k], own[k], p, discount)
            ps.insert(0, p)
        logs.append([np.log(np.maximum(x, 1e-12)) for x in ps])
    return keys, [(b - a).astype(np.float32) for a, b in zip(*logs, strict=True)]


def _evidence(batch: pa.RecordBatch, m: Model) -> np.ndarray:
    """For each text: mean log-likelihood ratio a symbol, symbols, the ratios of its three most toxic words, and how many words pass 2 and 4.

    The longest n-gram with an entry speaks for a symbol, else none does.
    """
    symbols, first = _symbols(batch)
    _, code = _codes(symbols, first, ORDER)
    value = np.zeros(len(code))
    open_ = np.arange(len(code))
    for k, (grams, ratios) in enumerate(zip(m.grams, m.ratios, strict=True)):
        at = _find(grams, code[open_] & ((1 << BITS * (ORDER - k)) - 1))
        value[open_[at >= 0]] = ratios[at[at >= 0]]
        open_ = open_[at < 0]
    total = np.concatenate([[0.0], np.cumsum(value)])
    n = np.maximum(np.diff(first) - 1, 0)
    out = np.zeros((len(n), 7))
    out[:, 0], out[:, 1] = (total[first[1:]] - total[first[:-1]]) / np.maximum(n, 1), n
    gaps = np.flatnonzero(symbols == 0)
    word = total[np.append(gaps[1:], len(symbols))] - total[gaps + 1] if len(gaps) else np.zeros(0)
    owner = np.searchsorted(first, gaps, "right") - 1
    order = np.lexsort((-word, owner))
    word, owner = word[order], owner[order]
    begin = np.searchsorted(owner, np.arange(len(n) + 1))
    for j in range(3):
        some = begin[:-1] + j < begin[1:]
        out[some, 2 + j] = word[begin[:-1][some] + j]
    for j, least in enumerate((2.0, 4.0)):
        out[:, 5 + j] = np.bincount(owner, word > least, len(n)) if len(n) else 0
    return out


FIELDS = [f"e{i}" for i in range(7)]


def _features(e: np.ndarray) -> np.ndarray:
    mean, n = e[:, 0], e[:, 1]
    words_ = n / 6 + 1
    return np.stack([np.ones(len(e)), mean * 20, mean * np.sqrt(n), np.log1p(n) - 6, e[:, 2] / 4, e[:, 3] / 4, e[:, 4] / 4, np.log1p(e[:, 5]), np.log1p(e[:, 6]), 50 * e[:, 5] / words_, 50 * e[:, 6] / words_], axis=1)


def _logistic(x: np.ndarray, y: np.ndarray, w: np.ndarray, ridge: float = 1.0) -> np.ndarray:
    b = np.zeros(x.shape[1])
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        h = (x * (w * p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(b))
        step = np.linalg.solve(h, x.T @ (w * (y - p)) - ridge * b)
        b += np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-8:
            break
    return b


def train(docs: DataFrame, labels: DataFrame, most: int = 6000, least: int = 4, discount: float = 0.75) -> Model | None:
    """Fit on docs(doc_id, text) and labels(doc_id, toxic); None without labelled documents of both classes.

    most: labelled documents a class that the class counts and the calibration use, those of the least hash of doc_id
    (the documented bound of the fit); two thirds give counts, the rest the calibration. The shared backoff counts
    cover every document. n-grams in fewer than `least` of the counted documents have no entry of their own. Null
    labels and ids are passed over; of several labels the greatest counts.
    """
    spark = docs.sparkSession
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    marked = labels.where("toxic is not null and doc_id is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    marked = marked.where("toxic in (0, 1)").withColumn("h", F.xxhash64("doc_id"))
    sizes = {r["toxic"]: r["count"] for r in marked.groupBy("toxic").count().collect()}
    if set(sizes) != {0, 1}:
        return None
    chosen = marked.where("toxic = 0").orderBy("h").limit(most).union(marked.where("toxic = 1").orderBy("h").limit(most))
    counted = F.pmod(F.xxhash64("h"), F.lit(3)) > 0
    sample = materialise(src.join(F.broadcast(chosen), "doc_id").select("text", "toxic", counted.alias("counted")))
    n = [F.sum(F.when(F.col("cls") == c, F.col("n")).otherwise(0)).alias(f"n{c}") for c in (0, 1)]
    kept = sample.where("counted").select("text", "toxic").mapInArrow(_class_counts, "cls int, gram long, n long").groupBy("gram").agg(*n).where(F.col("n0") + F.col("n1") >= least).toPandas().sort_values("gram")
    corpus = src.select("text").mapInArrow(_corpus_counts, "gram int, n long").groupBy("gram").agg(F.sum("n").alias("n")).toPandas().sort_values("gram")
    shared = corpus["gram"].to_numpy(np.int64), corpus["n"].to_numpy(float)
    model = Model(*fit_ratios(kept["gram"].to_numpy(np.int64), (kept["n0"].to_numpy(float), kept["n1"].to_numpy(float)), (shared[0], shared_probabilities(*shared, discount)), discount))
    held = spark.sparkContext.broadcast(model)

    def measure(batches):
        for whole in batches:
            for b in slices(whole, "text"):
                e = _evidence(b, held.value)
                yield pa.record_batch({f: np.ascontiguousarray(e[:, i]) for i, f in enumerate(FIELDS)} | {"toxic": col(b, "toxic").cast(pa.int32())})

    fit = sample.where("not counted").select("text", "toxic").mapInArrow(measure, ", ".join(f"{f} double" for f in FIELDS) + ", toxic int").orderBy(*FIELDS, "toxic").toPandas()
    y = fit["toxic"].to_numpy(float)
    share = {c: sizes[c] / max(1, (y == c).sum()) for c in (0, 1)}
    weights = np.where(y == 1, share[1], share[0])
    model.weights = _logistic(_features(fit[FIELDS].to_numpy()), y, weights / max(weights.mean(), 1e-9)) if len(y) else np.array([-2.0, 1, 1, *[0.0] * 8])
    return model


def score(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, score, predicted for every row of docs(doc_id, text); score is a probability, predicted is score >= 0.5.

    A text without letters, empty or null, has the score of a mean ratio of 0. Without a model all scores are 0.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by the fit's sample, not by the input

    def run(batches):
        for whole in batches:
            for b in slices(whole, "text"):
                m = shared.value
                if m is None:
                    s = np.zeros(b.num_rows)
                else:
                    s = 1 / (1 + np.exp(-np.clip(_features(_evidence(b, m)) @ m.weights, -30, 30)))
                yield pa.record_batch({"doc_id": col(b, "doc_id"), "score": s, "predicted": (s >= 0.5).astype(np.int32)})

    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return src.mapInArrow(run, "doc_id long, score double, predicted int")


def drop_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of docs that the model trained on the labelled ones doesn't reject; all columns stay."""
    model = train(docs, labels)
    bad = score(docs, model).where("predicted = 1").select("doc_id").distinct()
    return docs.join(bad, "doc_id", "left_anti").select(*docs.columns)
