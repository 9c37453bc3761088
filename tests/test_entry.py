import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = ["core_exact", "core_hierarchy", "sketch_batch_T3", "error_pct", "threshold_wave", "op_hindex", "op_core_cube", "approx_kcore", "graph_page_link", "op_vec_near", "op_param_grid", "sketch_levels"]


def test_entry_runs(spark):
    assert entry.entry(spark).count() > 0


def test_every_sql_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    cur = con.execute(entry.oracle_sql()[name])
    names = [x[0] for x in cur.description]
    want = cur.fetchall()
    df = entry.queries()[name](spark, sf_dir)
    assert sorted(df.columns) == sorted(names)
    got = [tuple(r[c] for c in names) for r in df.collect()]
    show = lambda rows: sorted(repr(tuple(round(x, 6) if isinstance(x, float) else x for x in r)) for r in rows)
    assert show(got) == show(want)


@pytest.mark.parametrize("name", ["op_param_grid", "sketch_levels"])
def test_query_reads_a_given_table(spark, sf_dir, name):
    assert any(f.endswith("lineitem.parquet") for f in entry.queries()[name](spark, sf_dir).inputFiles())


def test_near_vectors_in_several_blocks(spark, monkeypatch):
    from stratacore import sources

    monkeypatch.setattr(sources, "VECTOR_BLOCK", 7)
    rows = [(k, [float(k % 5), 1.0, float(k % 3)]) for k in range(40)] + [(40, None), (41, [3.0, 4.0])]
    unit = spark.createDataFrame(rows, "vec_id long, v array<double>")
    got = sorted(map(tuple, sources.near_pairs(unit, 6.0).collect()))
    dot = lambda x, y: sum(a * b for a, b in zip(x, y, strict=True))
    assert got == [(a, b) for a, x in rows[:40] for b, y in rows[:40] if a < b and dot(x, y) >= 6.0]
