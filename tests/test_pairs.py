"""Members that share groups, by blocks of bits: the same pairs, counts and triangles as plain joins."""

import duckdb
import pytest

import __spark_entry__ as entry
from stratacore.operators import pairs

GROUPS = ["graph_user_hour", "graph_user_hour_type", "degree_conc", "degree_conc_in", "op_triangles", "op_two_hop"]


@pytest.mark.parametrize("name", GROUPS)
def test_blocks_of_bits_equal_sql(spark, sf_dir, name, monkeypatch):
    monkeypatch.setattr(pairs, "PAIR_ROWS", 0)
    monkeypatch.setattr(pairs, "BLOCK", 70)
    monkeypatch.setattr(pairs, "STRIP_BYTES", 1000)
    con = duckdb.connect()
    for t in ("events", "pages"):
        con.execute(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    want = sorted(con.execute(entry.oracle_sql()[name]).fetchall())
    df = entry.queries()[name](spark, sf_dir)
    assert "CartesianProduct" not in df._jdf.queryExecution().toString()
    assert sorted(map(tuple, df.collect())) == want and want


def test_large_groups_are_not_joined(spark, tmp_path, monkeypatch):
    """500 users in one hour and a null: the pairs come from blocks, and no join of two members is planned."""
    monkeypatch.setattr(pairs, "PAIR_ROWS", 1000)
    monkeypatch.setattr(pairs, "BLOCK", 64)
    rows = spark.range(500).selectExpr("id AS event_id", "timestamp_seconds(id) AS ts", "nullif(id, 7) AS user_id", "'a' AS event_type")
    rows.write.parquet(f"{tmp_path}/events.parquet")
    df = entry.queries()["graph_user_hour"](spark, str(tmp_path))
    assert "PythonMapInArrow" in df._jdf.queryExecution().toString() or "MapInArrow" in df._jdf.queryExecution().toString()
    assert df.count() == df.distinct().count() == 499 * 498 // 2
    got = entry.queries()["op_triangles"](spark, str(tmp_path)).first()[0]
    per = [60 - (k == 0) for k in range(8)] + [20]
    assert got == sum(m * (m - 1) * (m - 2) // 6 for m in per)
