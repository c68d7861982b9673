"""Benchmark decontamination: rare n-gram seeds, then Smith-Waterman alignment over words."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.llm.textkit import LOOSE, LOWER, U, col, shingles, slices, span_hashes, text_bytes, words
from coverdp.runtime import materialise

#: Test items that are searched for at once; more of them take further passes, so what is broadcast is bounded.
BLOCK_ITEMS, BLOCK_BYTES = 20_000, 16_000_000


@dataclass(frozen=True)
class Rule:
    """seed: words of a seed; short: words of the second, shorter kind, used only where rare; rare: how many times the documents of an item's rarest seed a seed may have; similarity: matched words against the item's words; run: words of an aligned part that count as a leak at identity `tight`."""

    seed: int = 5
    short: int = 3
    rare: int = 8
    similarity: float = 0.8
    run: int = 25
    tight: float = 0.9


def _tokens(column: pa.Array):
    data, offs = text_bytes(column)
    data = LOWER[data]
    starts, ends, first = words(data, offs, LOOSE)
    return span_hashes(data, starts, ends), first


class Items:
    """A block of test items with the places of their seeds."""

    def __init__(self, ids: list[int], texts: list[str | None], rule: Rule) -> None:
        tokens, first = _tokens(pa.array(texts, pa.string()))
        self.ids, self.rule = ids, rule
        self.words = [tokens[first[i] : first[i + 1]] for i in range(len(ids))]
        keys, item, place = [], [], []
        for k in (rule.seed, rule.short):
            h, begin = shingles(tokens, first, k)
            for i in range(len(ids)):
                n = begin[i + 1] - begin[i]
                keys.append(h[begin[i] : begin[i + 1]] ^ U(k)), item.append(np.full(n, i)), place.append(np.arange(n))
        self.seed_long = np.concatenate([np.full(sum(map(len, keys[: len(ids)])), True), np.full(sum(map(len, keys[len(ids) :])), False)]) if ids else np.zeros(0, bool)
        key = np.concatenate(keys) if keys else np.zeros(0, U)
        order = np.argsort(key, kind="stable")
        self.key, self.seed_long = key[order], self.seed_long[order]
        self.item, self.place = (np.concatenate(x)[order] if x else np.zeros(0, np.int64) for x in (item, place))
        self.distinct = np.unique(self.key)
        self.usable = np.ones(len(self.key), bool)

    def judge(self, frequency: dict[int, int]) -> None:
        """Keep the rare seeds: those in few documents more than the rarest long seed of their item."""
        df = np.array([frequency.get(int(k), 0) for k in self.key.view(np.int64)], np.int64)
        floor = np.full(len(self.ids), np.iinfo(np.int64).max)
        live = df > 0
        np.minimum.at(floor, self.item[live & self.seed_long], df[live & self.seed_long])
        bound = np.minimum(floor, 1 << 40)[self.item] * self.rule.rare
        self.usable = live & np.where(self.seed_long, df <= bound, (df <= bound) & (floor[self.item] < 1 << 40) | (df <= self.rule.rare))

    def hits(self, tokens: np.ndarray, first: np.ndarray):
        """(text, word of the text, seed) of all seeds in texts."""
        for k in (self.rule.seed, self.rule.short):
            h, begin = shingles(tokens, first, k)
            h = h ^ U(k)
            lo = np.searchsorted(self.key, h, "left")
            n = np.searchsorted(self.key, h, "right") - lo
            at = np.flatnonzero(n)
            if len(at):
                many = n[at]
                text = np.searchsorted(begin, at, "right") - 1
                seed = np.repeat(lo[at], many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
                yield np.repeat(text, many), np.repeat(at - begin[text], many), seed


    def shared(self, text: np.ndarray, seed: np.ndarray) -> np.ndarray:
        """Of hits of one kind of seed, those of a text that holds enough different seeds of an item for a leak, however common they are.

        An edit spoils as many seeds as a seed has words. Half of what the edits of the rule leave is enough here, as
        added words spoil seeds too.
        """
        rule, pair = self.rule, text * np.int64(len(self.ids)) + self.item[seed]
        longest = max((len(w) for w in self.words), default=0) + 1
        each = np.unique(pair * longest + self.place[seed]) // longest
        pairs, n = np.unique(each, return_counts=True)
        size = np.array([len(w) for w in self.words], float)[pairs % len(self.ids)]
        if self.seed_long[seed[0]]:
            columns = rule.run / rule.tight
            least = np.full(len(pairs), (columns - rule.seed + 1 - rule.seed * (columns - rule.run)) / 2)
        else:
            least = (size - rule.short + 1 - rule.short * (1 - rule.similarity) * size) / 2
        return np.isin(pair, pairs[n >= np.maximum(1, np.floor(least))])


def align(a: np.ndarray, b: np.ndarray) -> tuple[int, int, int, int]:
    """Smith-Waterman, 1 for a match and -1 for a change or a gap: (matches, columns, first, end in b) of a best local alignment of word sequences.

    Each cell carries the matches, columns and first word of its alignment along, so two rows are held whatever the
    length of a. Of equal scores the first cell, by rows, counts; within a cell a pair goes before a gap.
    """
    m = len(b)
    at = np.arange(m, dtype=np.int32)
    score, matches, columns = (np.zeros(m + 1, np.int32) for _ in range(3))
    begin = np.arange(m + 1, dtype=np.int32)
    best = 0, 0, 0, 0, 0
    for word in a:
        same = b == word
        pair, gap = score[:-1] + np.where(same, 1, -1), score[1:] - 1
        own = np.maximum(np.maximum(pair, gap), 0)
        by_pair, none = pair == own, own == 0
        own_matches = np.where(none, 0, np.where(by_pair, matches[:-1] + same, matches[1:]))
        own_columns = np.where(none, 0, np.where(by_pair, columns[:-1], columns[1:]) + 1)
        own_begin = np.where(none, at + 1, np.where(by_pair, begin[:-1], begin[1:]))
        # gaps along the row: a running maximum of what falls by one a step, and where it was reached last
        reached = np.maximum.accumulate(own + at)
        source = np.maximum.accumulate(np.where(own + at == reached, at, 0))
        score[1:] = reached - at
        matches[1:], columns[1:], begin[1:] = own_matches[source], own_columns[source] + at - source, own_begin[source]
        begin[0] = 0
        top = int(score.argmax())
        if score[top] > best[0]:
            best = int(score[top]), int(matches[top]), int(columns[top]), int(begin[top]), top
    return best[1:]


def _count(shared):
    """Documents of each seed, summed a batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items = shared.value
        total = np.zeros(len(items.distinct), np.int64)
        for whole in batches:
            for b in slices(whole, "text"):
                tokens, first = _tokens(col(b, "text"))
                for text, _, seed in items.hits(tokens, first):
                    at = np.searchsorted(items.distinct, items.key[seed])
                    pairs = np.unique(text * np.int64(len(total)) + at)
                    np.add.at(total, pairs % len(total), 1)
        live = np.flatnonzero(total)
        yield pa.record_batch({"seed": items.distinct[live].view(np.int64), "n": total[live]})

    return run


def _search(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items, rule = shared.value, shared.value.rule
        for whole in batches:
            for b in slices(whole, "text"):
                tokens, first = _tokens(col(b, "text"))
                spots: dict[tuple[int, int], set[int]] = {}
                for text, word, seed in items.hits(tokens, first):
                    ok = items.usable[seed] | items.shared(text, seed)
                    for t, i, d in zip(text[ok].tolist(), items.item[seed[ok]].tolist(), (word[ok] - items.place[seed[ok]]).tolist(), strict=True):
                        spots.setdefault((t, i), set()).add(d)
                out = []
                for (t, i), diagonals in spots.items():
                    item = items.words[i]
                    own = tokens[first[t] : first[t + 1]]
                    slack, best, done = max(8, len(item) // 3), None, -1
                    for d in sorted(diagonals):
                        lo, hi = max(0, d - slack), min(len(own), d + len(item) + slack)
                        if hi <= done:
                            continue
                        done = hi
                        matches, columns, begin, end = align(item, own[lo:hi])
                        if best is None or matches > best[0]:
                            best = matches, columns, lo + begin, lo + end
                    matches, columns, begin, end = best
                    share = matches / max(1, len(item))
                    if share >= rule.similarity or matches >= rule.run and matches >= rule.tight * columns:
                        out.append((t, items.ids[i], share, begin, end, matches))
                if out:
                    t, item, share, begin, end, matches = zip(*out, strict=True)
                    yield pa.record_batch({"doc_id": col(b, "doc_id").take(pa.array(t)), "item_id": pa.array(item, pa.int64()), "similarity": pa.array(share, pa.float64()), "first_word": pa.array(begin, pa.int64()), "end_word": pa.array(end, pa.int64()), "matches": pa.array(matches, pa.int64())})

    return run


def _blocks(benchmark: DataFrame):
    ids, texts, size = [], [], 0
    for r in benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("item_id is not null and text is not null").orderBy("item_id", "text").toLocalIterator():
        ids.append(r["item_id"]), texts.append(r["text"])
        size += len(r["text"])
        if len(ids) >= BLOCK_ITEMS or size >= BLOCK_BYTES:
            yield ids, texts
            ids, texts, size = [], [], 0
    if ids:
        yield ids, texts


def find_leaks(docs: DataFrame, benchmark: DataFrame, rule: Rule = Rule()) -> DataFrame:
    """doc_id, item_id, similarity, first_word, end_word, matches: documents that hold a test item or an edited copy.

    Words are runs of letters and digits, A-Z lower-cased. Every whole text is searched for every item; items come in
    blocks of bounded size. A pair is aligned if it shares a seed about as rare among
    all documents as its item's rarest, or enough seeds of any frequency for a leak. A pair is a
    leak if `similarity` of the item's words are matched, or `run` words at an identity of `tight`. Items and texts
    without words match nothing; empty tables give no rows; several rows of a doc_id may give a row each.
    """
    spark = docs.sparkSession
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("text is not null")
    found = spark.createDataFrame([], "doc_id long, item_id long, similarity double, first_word long, end_word long, matches long")
    for ids, texts in _blocks(benchmark):
        items = Items(ids, texts, rule)
        counted = src.select("text").mapInArrow(_count(spark.sparkContext.broadcast(items)), "seed long, n long").groupBy("seed").agg(F.sum("n").alias("n"))
        items.judge({r["seed"]: r["n"] for r in counted.collect()})  # as many rows as the block has seeds, at most
        found = found.union(src.mapInArrow(_search(spark.sparkContext.broadcast(items)), found.schema))
    return found


def drop_leaks(docs: DataFrame, benchmark: DataFrame, rule: Rule = Rule()) -> DataFrame:
    """The rows of docs without a leak; all columns stay."""
    bad = materialise(find_leaks(docs, benchmark, rule).select("doc_id").distinct())
    return docs.join(bad, "doc_id", "left_anti").select(*docs.columns)
