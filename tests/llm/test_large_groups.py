"""Groups of hundreds and thousands of distinct near copies."""

import random
import sys
from pathlib import Path

sys.path.insert(0, str(Path(__file__).parent))
import brute  # noqa: E402

from coverdp.llm import neardup, paragraphs  # noqa: E402


def copies(n, edits, k, seed, words=100):
    """Distinct one-line texts, all at 0.8 or more to the one in the middle; no two edits use the same word."""
    rnd = random.Random(seed)
    base = [f"w{rnd.randrange(10**6)}" for _ in range(words)]
    sets = brute.shingle_sets([(0, " ".join(base))], k)[0]
    out = []
    while len(out) < n:
        own = list(base)
        for _ in range(rnd.randint(1, edits)):
            own[rnd.randrange(words)] = f"x{rnd.randrange(10**9)}"
        s = brute.shingle_sets([(0, " ".join(own))], k)[0]
        if 100 * len(s & sets) >= 80 * len(s | sets):
            out.append(" ".join(own))
    out.insert(n // 2, " ".join(base))
    return out


def lines(docs):
    """The document of the cluster of each document's one line."""
    return {r["doc_id"]: r["cluster"] // paragraphs.PLACES for r in paragraphs.paragraph_clusters(docs).where("kind = 0").collect()}


def test_paragraphs_of_a_large_group(spark):
    for n in (300, 2000):
        texts = copies(n, 2, 5, n)
        docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
        got = lines(docs)
        if n == 300:
            assert set(brute.linked(brute.shingle_sets(list(enumerate(texts)), 5)).values()) == {0}
        assert got == {i: 0 for i in range(n + 1)}


def test_paragraphs_of_unlike_groups_in_one_bucket(spark):
    # a common opening fills buckets with groups that aren't linked to each other
    rnd, texts = random.Random(3), []
    opening = " ".join(f"o{i}" for i in range(50))
    for g in range(40):
        tail = [f"g{g}t{i}" for i in range(50)]
        for _ in range(10):
            own = list(tail)
            own[rnd.randrange(50)] = f"x{rnd.randrange(10**9)}"
            texts.append(f"{opening} {' '.join(own)}")
    rnd.shuffle(texts)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = brute.linked(brute.shingle_sets(list(enumerate(texts)), 5))
    assert lines(docs) == want


def test_documents_of_a_large_group(spark):
    for n, edits, k in ((300, 4, 2), (2000, 4, 2), (2000, 2, 5)):
        docs = spark.createDataFrame(list(enumerate(copies(n, edits, k, n))), "doc_id long, text string")
        got = neardup.near_duplicates(docs, k).select("doc_id", "component_id").collect()
        assert len(got) == n + 1 and sum(r["component_id"] != 0 for r in got) == 0
