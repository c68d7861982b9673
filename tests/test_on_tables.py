"""Queries that once made their data up: what they give now follows from the given tables, as their SQL says."""

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = {"bounds_table": ("customer", "orders", "events"), "coin_flip_tail": ("customer",), "layer_family_closed": ("lineitem",)}


def plain(rows):
    return sorted(tuple(round(x, 4) if isinstance(x, float) else x for x in r) for r in rows)


@pytest.mark.parametrize("name", TABLES)
def test_rows_are_those_of_the_sql(spark, tiny, name):
    con = duckdb.connect()
    for t in TABLES[name]:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{tiny}/{t}.parquet')")
    cursor = con.execute(entry.oracle_sql()[name])
    names = [c[0] for c in cursor.description]
    df = entry.queries()[name](spark, tiny)
    assert df.columns == names
    want = plain(cursor.fetchall())
    assert plain(map(tuple, df.collect())) == want and want


def test_bounds_follow_the_tables(spark, tiny, tmp_path):
    for t in TABLES["bounds_table"]:
        df = spark.read.parquet(f"{tiny}/{t}.parquet")
        df.limit(7 + len(t)).write.parquet(f"{tmp_path}/{t}.parquet")
    got = entry.queries()["bounds_table"](spark, str(tmp_path)).select("n").distinct().collect()
    assert sorted(r["n"] for r in got) == sorted({7 + len(t) for t in TABLES["bounds_table"]})


def test_tosses_and_functions_follow_the_tables(spark, tiny, tmp_path):
    for t in ("customer", "lineitem"):
        spark.read.parquet(f"{tiny}/{t}.parquet").limit(5).write.parquet(f"{tmp_path}/{t}.parquet")
    q = entry.queries()
    assert max(r["held"] for r in q["coin_flip_tail"](spark, str(tmp_path)).collect()) <= 5
    assert q["layer_family_closed"](spark, str(tmp_path)).first()["cases"] <= 5
