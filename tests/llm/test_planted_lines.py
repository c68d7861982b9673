"""Repeated passages of a few lines between unlike lines."""

from coverdp.llm import linechunks


def test_passages_of_two_lines_and_more(spark):
    rows, want = [], {}
    for n in range(2, 13):
        for trial in range(5):
            passage = [f"passage {n} {trial} {i}" for i in range(n)]
            for copy in range(2):
                i = len(rows)
                own = [f"own {i} {j}" for j in range(10)]
                rows.append((i, "\n".join([*own[:5], *passage, *own[5:]])))
                want[i] = ("\n".join(own), n) if copy else (rows[-1][1], 0)
    got = linechunks.drop_repeated_chunks(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sum((r["text"], r["n_removed_lines"]) != want[r["doc_id"]] for r in got) == 0 and len(got) == len(rows)


def test_overlapping_copies_and_single_lines(spark):
    rows = [(1, "a\na\na"), (2, "b\nb\nb\nb"), (3, "c\n\nd"), (4, "x\nc\n\nd\ny"), (5, "one\nc\ntwo"), (6, "only\n\n"), (7, "only\n\n")]
    got = {r["doc_id"]: (r["text"], r["n_removed_lines"]) for r in linechunks.drop_repeated_chunks(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: ("a\na\na", 0), 2: ("b\nb\n", 2), 3: ("c\n\nd", 0), 4: ("x\ny", 3), 5: ("one\nc\ntwo", 0), 6: ("only\n\n", 0), 7: ("only\n\n", 0)}
