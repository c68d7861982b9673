"""Nulls, empty and very long texts, repeated rows, empty tables and clashing columns."""

import pytest
from pyspark.sql import functions as F

from coverdp.llm import bpe, decontaminate, langid, linechunks, neardup, paragraphs, quality, substrings, toxicity, warc
from coverdp.llm.queries import codec

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, n_removed_lines string, spans string"
LONG = "word " * 30_000


@pytest.fixture(scope="module")
def odd(spark):
    line = "one two three four five six seven eight nine ten eleven twelve"
    rows = [(1, None, "en", "a", 0, "x", "y"), (2, "", None, None, 0, "x", "y"), (3, " \n ", "en", None, 3, "x", "y"), (4, LONG, "en", "a", 9, None, None), (5, f"{line}\n{line} x", None, "a", 9, "x", "y"), (6, f"{line}\n{line} x", "de", "a", 9, "x", "y"), (7, "word", "de", "b", 4, None, None), (None, "lost", "de", "b", 4, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_near_duplicates(odd, empty):
    got = {r["doc_id"]: r for r in neardup.near_duplicates(odd).collect()}
    assert len(got) == 8 and got[6]["component_id"] == 5 and not got[6]["kept"]
    assert all(got[i]["n_shingles"] == 0 and got[i]["kept"] for i in (1, 2, 3))
    assert neardup.near_duplicates(empty).count() == 0


def test_paragraphs(odd, empty):
    got = {r["doc_id"]: r for r in paragraphs.removals(odd, least_words=5).collect()}
    whole = sum(len(x) + 1 for x in ("one two three four five six seven eight nine ten eleven twelve",) * 2) + 1
    assert len(got) == 8 and [tuple(x) for x in got[6]["removed"]] == [(0, whole)] and got[1]["n_removed"] == 0
    assert paragraphs.removals(empty).count() == 0
    clash = odd.withColumn("gone", F.lit("z"))
    cut = {r["doc_id"]: r for r in paragraphs.drop_repeated_paragraphs(clash, least_words=5).collect()}
    assert len(cut) == 8 and cut[6]["text"] == "" and cut[6]["gone"] == "z" and cut[1]["text"] is None and cut[5]["text"].count("\n") == 1
    assert paragraphs.drop_repeated_paragraphs(empty).columns == empty.columns


def test_line_chunks(odd, empty):
    got = {r["doc_id"]: r for r in linechunks.drop_repeated_chunks(odd).collect()}
    assert len(got) == 8 and got[1]["text"] is None and got[5]["n_removed_lines"] == 0 and got[6]["n_removed_lines"] == 2 and got[6]["text"] == ""
    assert linechunks.drop_repeated_chunks(empty).count() == 0


def test_substrings(odd, empty):
    got = {r["doc_id"]: r for r in substrings.remove_repeats(odd).collect()}
    assert len(got) == 7 and got[6]["n_removed"] == got[6]["n_bytes"] and got[4]["n_removed"] == 0 and got[1]["n_bytes"] == 0
    assert substrings.remove_repeats(empty).count() == 0


def test_language(odd, empty):
    got = {r["doc_id"]: r for r in langid.identify(odd, langid.train(odd)).collect()}
    assert got[1]["lang_pred"] == got[2]["lang_pred"] == got[3]["lang_pred"] == "und" and got[4]["lang_pred"] == "en"
    assert langid.identify(odd, langid.train(empty)).where("lang_pred <> 'und'").count() == 0


def test_toxicity(spark, odd, empty):
    labels = spark.createDataFrame([(4, 1), (7, 0), (5, None), (None, 1), (4, 0)], "doc_id long, toxic int")
    model = toxicity.train(odd, labels)
    assert toxicity.score(odd, model).where("score between 0 and 1").count() == 8
    assert toxicity.train(odd, labels.limit(0)) is None and toxicity.score(empty, None).count() == 0


def test_quality(odd, empty):
    got = {r["doc_id"]: r for r in quality.quality_rules(odd).collect()}
    assert len(got) == 8 and got[4]["n_words"] == got[4]["n_repeat_words"] == 30_000 and got[4]["base_failed"] and got[1]["n_words"] == 0
    assert quality.quality_rules(empty).count() == 0


def test_leaks(spark, odd, empty):
    items = spark.createDataFrame([(1, "one two three FOUR, five six seven eight nine ten eleven"), (2, None), (3, ""), (None, "word")], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.find_leaks(odd, items).collect()}
    assert got == {(5, 1), (6, 1)}
    assert decontaminate.find_leaks(empty, items).count() == decontaminate.find_leaks(odd, items.limit(0)).count() == 0


def test_bpe(odd, empty):
    c = codec()
    back = {r["doc_id"]: bytes(r["payload"]) for r in bpe.decode(bpe.encode(odd, c), c).collect()}
    assert back[1] == b"" and back[4] == LONG.encode() and len(back) == 8
    assert bpe.round_trip(empty, c).count() == 0


def test_warc(spark):
    html = "<p>ä</p>" * 5000
    pages = spark.createDataFrame([(1, "http://a b", html), (2, None, html), (3, "u", None), (4, "u", "x"), (5, "u", "x")], "page_id long, url string, html string")
    got = {r["page_id"]: r for r in warc.archive_pages(pages).collect()}
    assert got[2]["refers_to"] == 1 and got[2]["payload_bytes"] == len(html.encode()) == got[1]["payload_bytes"]
    assert got[3]["payload_bytes"] == 0 and got[5]["record_type"] == "response"
    assert warc.archive_pages(pages.limit(0)).count() == 0
    with pytest.raises(ValueError):
        warc.dechunk(b"5\r\nabc\r\n0\r\n\r\n")
