"""Outliers planted in a large and in small groups of language and source."""

import random

from coverdp.llm import quality


def test_outliers_of_small_groups(spark):
    rnd, rows, odd = random.Random(5), [], set()

    def add(lang, source, strange):
        word = (lambda: "".join(rnd.choice("abcdefgh") for _ in range(40))) if strange else lambda: "".join(rnd.choice("abcdefgh") for _ in range(rnd.randint(3, 8)))
        if strange:
            odd.add(len(rows))
        rows.append((len(rows), " ".join(word() for _ in range(rnd.randint(80, 120))), lang, source))

    for i in range(200):
        add("en", "hot", i % 50 == 7)
    for tail in range(20):  # sources of five documents, judged by their language
        for i in range(5):
            add("en", f"tail{tail}", tail < 3 and i == 2)
    for i in range(6):  # a language of six, judged by all
        add("de", "only", i == 3)
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    got = quality.quality_rules(docs).collect()
    assert {r["doc_id"] for r in got if not r["kept"]} == odd and len(got) == len(rows)
