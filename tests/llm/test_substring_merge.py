"""Merged transforms against plain sorting, hot grams, and a whole small table against brute force."""

import sys
from pathlib import Path

import numpy as np
import pandas as pd

sys.path.insert(0, str(Path(__file__).parent))
import brute  # noqa: E402

from coverdp.llm import substrings as S  # noqa: E402


def test_intervals_of_unequal_strings():
    rnd = np.random.RandomState(5)
    for _ in range(20):
        shards = [[bytes(rnd.choice([97, 98], rnd.randint(6, 30)).astype(np.uint8)) for _ in range(rnd.randint(1, 5))] for _ in range(4)]
        docs = [rnd.randint(0, 50, len(s)) for s in shards]
        least: dict[bytes, int] = {}
        flat = [(x, d) for s, own in zip(shards, docs, strict=True) for x, d in zip(s, own.tolist(), strict=True)]
        for x, d in flat:
            for p in range(len(x) - 5):
                least[x[p : p + 6]] = min(d, least.get(x[p : p + 6], d))
        want = [[least[x[p : p + 6]] for p in range(len(x) - 5)] for x, _ in flat]
        assert [x.tolist() for x in S.least_documents(shards, docs, 6)] == want


def test_whole_table_and_hot_grams(spark):
    docs = pd.read_parquet("/root/testdata/sf0.01/documents.parquet")
    want = brute.repeats(list(zip(docs.doc_id, docs.text, strict=True)))
    src = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").repartition(6, "doc_id")
    for hot in (S.HOT_PARTS, 1):  # the second deals the windows of every gram that two parts report one by one
        got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], len(r["removed"])) for r in S.remove_repeats(src, hot_parts=hot).collect()}
        assert got == {i: x[:3] for i, x in want.items()}


def test_views_of_long_texts():
    data = np.random.RandomState(2).randint(97, 100, 3 * S.VIEW_BYTES + 12_345).astype(np.uint8)
    offs = np.array([0, 10, 2 * S.VIEW_BYTES + 77, 2 * S.VIEW_BYTES + 77, len(data)])
    _, at, key = S.window_keys(data, offs, 50)
    found = [(offs[rows[t]] + shift[t] + a - o[t], k) for rows, shift, d, o in S._views(data, offs, 50) for t, a, k in [S.window_keys(d, o, 50)]]
    assert np.concatenate([x[0] for x in found]).tolist() == at.tolist() and (np.concatenate([x[1] for x in found]) == key).all()


def test_turns_share_the_runs(spark, monkeypatch):
    docs = pd.read_parquet("/root/testdata/sf0.001/documents.parquet")
    want = brute.repeats(list(zip(docs.doc_id, docs.text, strict=True)))
    src = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").repartition(3, "doc_id")
    monkeypatch.setattr(S, "TURN_BYTES", 1 << 17)
    write, runs = S.materialise, []

    def counted(df):
        out = write(df)
        if "raw" in out.columns:
            runs.append(out.where("bucket >= 0").count())
        return out

    monkeypatch.setattr(S, "materialise", counted)
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], len(r["removed"])) for r in S.remove_repeats(src).collect()}
    assert got == {i: x[:3] for i, x in want.items()}
    assert len(runs) > 1 and max(runs) < 0.6 * sum(runs)  # no turn exchanges most of the texts
