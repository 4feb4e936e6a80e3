"""A few registered queries against their SQL twins, and the shape of the entry module."""

import os

import pytest

SF = "/root/testdata/sf0.001"


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the given tables")
@pytest.mark.parametrize("name", ["prep_melt_cells", "prop_missing_rate", "sim_name", "graph_stats", "walk_slots", "match_mutual", "eval_f1", "rel_asof_join", "stream_dedup"])
def test_twin(spark, name):
    import duckdb

    import __spark_entry__ as entry
    from tools.compare import TABLES, rows_of

    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = entry.queries()[name](spark, SF)
    cur = con.execute(entry.oracle_sql()[name])
    cols = [c[0] for c in cur.description]
    assert sorted(cols) == sorted(df.columns)
    assert rows_of(df.columns, df.collect()) == rows_of(cols, cur.fetchall())


def test_every_twin_has_a_query():
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
