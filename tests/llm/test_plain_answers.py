"""Operators against plain definitions: bundles, alignments, repeated lines, robust distances, the pipeline's stages."""

import random
import sys
import tracemalloc
from pathlib import Path

import numpy as np
import pandas as pd

sys.path.insert(0, str(Path(__file__).parents[2]))

from pyspark.sql import functions as F  # noqa: E402

from coverdp.llm import decontaminate, langid, linechunks, quality, toxicity  # noqa: E402


def table_align(a, b):
    """The best local score by the full table."""
    score = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i, x in enumerate(a, 1):
        for j, y in enumerate(b, 1):
            score[i][j] = max(0, score[i - 1][j - 1] + (1 if x == y else -1), score[i - 1][j] - 1, score[i][j - 1] - 1)
    return max(map(max, score))


def test_alignment_by_two_rows():
    rnd = random.Random(4)
    for _ in range(200):
        a, b = ([rnd.randrange(4) for _ in range(rnd.randrange(1, 14))] for _ in range(2))
        matches, columns, first, end = decontaminate.align(np.array(a), np.array(b))
        assert matches - (columns - matches) == table_align(a, b)
        if matches:
            assert table_align(a, b[first:end]) == table_align(a, b) and b[first] in a and b[end - 1] in a
    tracemalloc.start()
    long = np.arange(4000)
    assert decontaminate.align(long, long)[:2] == (4000, 4000)
    assert tracemalloc.get_traced_memory()[1] < 4_000_000
    tracemalloc.stop()


def test_leaks_by_all_alignments(spark, tiny):
    docs, items = pd.read_parquet(f"{tiny}/documents.parquet"), pd.read_parquet(f"{tiny}/benchmark.parquet")
    import pyarrow as pa

    tokens = lambda texts: [h[f[i] : f[i + 1]] for h, f in [decontaminate._tokens(pa.array(texts, pa.string()))] for i in range(len(texts))]
    own, rule, want = tokens(items.text.tolist()), decontaminate.Rule(), set()
    for d, words in zip(docs.doc_id, tokens(docs.text.tolist()), strict=True):
        if len(words):
            for i, item in zip(items.item_id, own, strict=True):
                if len(np.intersect1d(item, words)) < min(rule.similarity * len(np.unique(item)), rule.run) / 2:
                    continue  # too few common words for any leak
                matches, columns, _, _ = decontaminate.align(item, words)
                if matches >= rule.similarity * len(item) or matches >= rule.run and matches >= rule.tight * columns:
                    want.add((d, i))
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.find_leaks(spark.createDataFrame(docs[["doc_id", "text"]]), spark.createDataFrame(items)).collect()}
    assert got == want and want


def test_bundles_by_a_plain_loop():
    texts = ["the cat", "", None, "Über 9 den Fluss!", "a"]
    dim = 64
    first, second, third = langid._places(dim, 7)
    got = langid._bundles(texts, dim, 7)
    classes = langid._letter_classes()
    for row, text in zip(got, texts, strict=True):
        letters = [int(classes[ord(c)]) for c in f" {(text or '').lower()} "]
        letters = [c for i, c in enumerate(letters) if c or not i or letters[i - 1]]
        want = np.zeros(dim)
        for x, y, z in zip(letters, letters[1:], letters[2:]):
            want += first[x].astype(int) * second[y] * third[z]
        assert (row == want).all()


def test_kneser_ney_by_definition():
    # every context's probabilities over the symbols add up to one, seen or not
    rnd = np.random.RandomState(1)
    text = rnd.randint(1, 5, 400)
    code = np.array([sum(int(text[i - j]) << (toxicity.BITS * j) for j in range(4)) for i in range(3, 400)])
    grams, counts = np.unique(code, return_counts=True)
    p = toxicity.shared_probabilities(grams, counts.astype(float), 0.75)
    assert ((p > 0) & (p < 1)).all()
    context = grams >> toxicity.BITS
    for c in np.unique(context):
        own = context == c
        n, kinds = counts[own].sum(), own.sum()
        assert p[own].sum() <= 1 + 1e-9  # the rest is left to unseen symbols
        assert (p[own] >= (counts[own] - 0.75) / n - 1e-12).all() and p[own].sum() >= 1 - 0.75 * kinds / n - 1e-9


def test_line_windows_by_a_plain_loop(spark):
    docs = pd.read_parquet("/root/testdata/sf0.01/documents.parquet")[["doc_id", "text"]]
    first: dict[tuple[str, str], tuple[int, int]] = {}
    windows = {}
    for d, text in sorted(zip(docs.doc_id, docs.text, strict=True)):
        lines = (text or "").split("\n")
        full = [i for i, x in enumerate(lines) if x.translate({c: None for c in (32, *range(9, 14))})]
        windows[d] = [(a, z, "\n".join(lines[a : z + 1])) for a, z in zip(full, full[1:])]
        for a, z, raw in windows[d]:
            first.setdefault(raw, (d, z))
    got = {r["doc_id"]: r["n_removed_lines"] for r in linechunks.drop_repeated_chunks(spark.createDataFrame(docs)).collect()}
    for d, own in windows.items():
        gone: set[int] = set()
        for a, z, raw in own:
            f = first[raw]
            if f[0] != d or f[1] < a:
                gone |= set(range(a, z + 1))
        assert got[d] == len(gone), d


def test_distances_by_numpy(spark):
    """The verdict's last step: distances fall off as for the estimate of the rows that aren't planted."""
    rnd = np.random.RandomState(3)
    rows = [(i, " ".join("w" * rnd.randint(3, 8) + str(rnd.randint(10**6)) for _ in range(rnd.randint(80, 400))), "en", "a") for i in range(300)]
    rows += [(1000 + i, " ".join("#$%" * 9 + str(rnd.randint(10**6)) for _ in range(200)), "en", "a") for i in range(9)]
    got = quality.quality_rules(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).toPandas().set_index("doc_id").sort_index()
    assert not got.loc[1000:].kept.any() and got.loc[:299].kept.mean() > 0.98
    f = np.array([[np.log1p(r.n_words), r.word_chars / r.n_words, (r.n_symbols / r.n_words) ** 0.5, (r.n_repeat_words / r.n_words) ** 0.5] for r in got.itertuples()])
    clean = f[:300]
    cov = np.cov(clean.T, bias=True) + np.diag([(x / 2) ** 2 for x in quality.FLOOR[:4]])
    plain = np.einsum("ij,jk,ik->i", f - clean.mean(0), np.linalg.inv(cov), f - clean.mean(0))
    assert np.corrcoef(np.argsort(np.argsort(plain)), np.argsort(np.argsort(got.distance.to_numpy())))[0, 1] > 0.9


def test_pipeline_stages(spark, tiny):
    import corpus_pipeline as C

    assert [n for n, _ in C.STAGES] == ["toxicity", "line_dedup", "near_dedup", "decontamination", "byte_bpe"]
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    before = docs.toPandas()
    for name, stage in C.STAGES[:-1]:
        out = stage(spark, docs, tiny).select(*docs.columns)
        after = out.toPandas()
        assert set(after.doc_id) <= set(before.doc_id) and len(after) == after.doc_id.nunique(), name
        same = after.merge(before, on="doc_id", suffixes=("", "_old"))
        assert name == "line_dedup" or (same.text.fillna("") == same.text_old.fillna("")).all()
        if name == "line_dedup":
            assert len(after) == len(before)
        docs, before = spark.createDataFrame(after, docs.schema), after
    last = C.STAGES[-1][1](spark, docs, tiny)
    assert last.count() == len(before) > 0


def test_pipeline_stages_on_odd_rows(spark, tiny):
    import corpus_pipeline as C

    schema = "doc_id long, text string, lang string, source string, n_chars long, removed_spans string, kept string"
    rows = [(1, None, None, None, None, "a", "b"), (2, "", "en", "x", 0, "a", "b"), (3, "same words " * 40, "en", "x", 440, "a", "b"), (3, "same words " * 40, "en", "x", 440, "a", "b"), (None, "no id", "en", "x", 5, "a", "b")]
    for docs in (spark.createDataFrame(rows, schema), spark.createDataFrame([], schema)):
        for _, stage in C.STAGES[:-1]:
            out = stage(spark, docs, tiny)
            assert out.columns == docs.columns and out.count() <= docs.count()
            assert out.where(F.col("doc_id") == 2).count() == docs.where(F.col("doc_id") == 2).count()
        assert C.STAGES[-1][1](spark, docs, tiny).count() == docs.count()
