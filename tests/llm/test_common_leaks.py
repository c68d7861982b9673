"""Edited test items with many near copies beside an exact one."""

import random

from coverdp.llm import decontaminate


def test_many_edited_copies_beside_an_exact_one(spark):
    rnd = random.Random(1)
    item = [f"w{i}" for i in range(60)]
    rows = [(0, " ".join(item))]
    for i in range(1, 41):
        own = list(item)
        own[30] = "changed"  # alike in all copies, so that all whole seeds but those over this word are common
        rows.append((i, " ".join([*(f"f{rnd.randrange(10**6)}" for _ in range(20)), *own])))
    for i in range(41, 61):
        own = [f"e{i}" if j % 5 == 4 else w for j, w in enumerate(item)]
        rows.append((i, " ".join(own)))
    rows += [(i, " ".join(f"f{rnd.randrange(10**6)}" for _ in range(80))) for i in range(61, 70)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    items = spark.createDataFrame([(7, " ".join(item))], "item_id long, text string")
    got = {r["doc_id"] for r in decontaminate.find_leaks(docs, items).collect()}
    assert len(set(range(61)) - got) == 0 and got == set(range(61))
