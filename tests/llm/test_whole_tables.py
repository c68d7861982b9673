"""The ten queries and the pipeline over the smallest tables, against plain answers."""

import hashlib
import sys
from pathlib import Path

import pandas as pd
import pytest

sys.path.insert(0, str(Path(__file__).parent))
import brute  # noqa: E402

from coverdp.llm import queries as Q  # noqa: E402


@pytest.fixture(scope="module")
def docs(tiny):
    return pd.read_parquet(f"{tiny}/documents.parquet")


def rows(docs):
    return list(zip(docs.doc_id, docs.text, strict=True))


def test_near_dedup(spark, tiny, docs):
    got = Q.op1_minhash_near_dedup(spark, tiny).toPandas().set_index("doc_id")
    sets = brute.shingle_sets(rows(docs), 2)
    want = brute.linked(sets)
    assert got.component_id.to_dict() == want
    assert got.n_shingles.to_dict() == {i: len(s) for i, s in sets.items()}
    assert (got.kept == (got.index == got.component_id)).all()


def test_language(spark, tiny, docs):
    got = Q.op2_language_id(spark, tiny).toPandas().merge(docs, on="doc_id")
    held = got[got.held_out & got.lang.notna()]
    assert len(got) == len(docs) and (held.lang == held.lang_pred).mean() > 0.9
    assert got.score.between(0, 1).all()


def test_leaks(spark, tiny, docs):
    got = Q.op3_decontamination(spark, tiny).toPandas()
    items = pd.read_parquet(f"{tiny}/benchmark.parquet")
    plain = {(d, i) for d, t in rows(docs) for i, x in zip(items.item_id, items.text, strict=True) if x in t}
    assert plain <= set(zip(got.doc_id, got.item_id, strict=True))
    assert (got.similarity <= 1).all()


def test_toxicity(spark, docs):
    got = Q.op4_toxicity(spark, "/root/testdata/sf0.01").toPandas()
    labels = pd.read_parquet("/root/testdata/sf0.01/labels.parquet")
    held = got[got.held_out].merge(labels, on="doc_id")
    assert got.score.between(0, 1).all() and (got.predicted == (got.score >= 0.5)).all()
    assert ((held.predicted == held.toxic).mean()) > 0.9


def test_warc(spark, tiny):
    pages = pd.read_parquet(f"{tiny}/pages.parquet")
    got = Q.op5_warc(spark, tiny).toPandas().set_index("page_id")
    first = {}
    for i, html in sorted(zip(pages.page_id, pages.html, strict=True)):
        raw = (html or "").encode()
        again = len(raw) >= 100 and raw in first
        first.setdefault(raw, i)
        r = got.loc[i]
        assert (r.payload_bytes, r.payload_digest) == (len(raw), hashlib.sha256(raw).hexdigest())
        assert r.record_type == ("revisit" if again else "response")
        assert (r.refers_to == first[raw]) if again else pd.isna(r.refers_to)
    assert len(got) == len(pages)


def test_bpe(spark, tiny, docs):
    import base64

    import public_tokenizers as P
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(P.path("byte_bpe_50k.tiktoken"), "rb"))}
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = Q.op6_byte_bpe(spark, tiny).toPandas().set_index("doc_id")
    for i, t in rows(docs):
        ids = enc.encode_ordinary(t or "")
        assert tuple(got.loc[i]) == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest())


def test_substrings(spark, tiny, docs):
    got = Q.op7_substring_dedup(spark, tiny).toPandas().set_index("doc_id")
    assert {i: tuple(r) for i, r in got.iterrows()} == brute.repeats(rows(docs))


def test_paragraphs(spark, tiny, docs):
    got = Q.op8_paragraph_dedup(spark, tiny).toPandas().set_index("doc_id")
    units = {(i, *u[:2]): u for i, t in rows(docs) for u in brute.paragraphs(t)}
    gone: dict[int, set[int]] = {i: set() for i in docs.doc_id}
    for kind in (0, 1):
        own = sorted(k for k in units if k[2] == kind)
        want = brute.linked(brute.shingle_sets([(k, units[k][4]) for k in own], 5))
        for k, c in want.items():
            if k != c:
                gone[k[0]] |= set(range(units[k][2], units[k][3]))
    assert len(got) == len(docs) and sum(map(len, gone.values())) > 0
    for i, want in gone.items():
        assert {x for g in got.loc[i].removed for x in range(g["at"], g["stop"])} == want
        assert got.loc[i].n_removed == sum(x - 1 not in want for x in want)


def test_quality(spark, tiny, docs):
    got = Q.op9_quality_rules(spark, tiny).toPandas().set_index("doc_id")
    for i, t in rows(docs):
        want = brute.base_statistics(t)
        r = got.loc[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want
        assert r.base_failed == (want[0] < 50 or 100 * want[4] > 50 * want[0])
        assert not (r.base_failed and r.kept)
    fine = got[~got.base_failed]
    assert fine.kept.mean() > 0.8


def test_line_chunks(spark, tiny, docs):
    from coverdp.llm import linechunks
    from coverdp.runtime import table

    got = linechunks.drop_repeated_chunks(table(spark, tiny, "documents")).toPandas()
    assert len(got) == len(docs) and (got.n_removed_lines >= 0).all()
    both = got.merge(docs, on="doc_id", suffixes=("", "_old"))
    seen = set()
    for r in both.sort_values("doc_id").itertuples():
        if r.text_old in seen and r.text_old.count("\n") >= 1:
            assert len(r.text) < len(r.text_old)
        if r.n_removed_lines == 0:
            assert r.text == r.text_old
        seen.add(r.text_old)
    assert got.n_removed_lines.sum() > 0
