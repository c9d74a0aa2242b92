import os

import pytest

import __spark_entry__


def test_registry():
    queries, oracles = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    assert set(oracles) <= set(queries) and len(queries) > 70 and len(oracles) > 50


@pytest.mark.skipif(not os.path.isdir("/root/testdata/sf0.001"), reason="no given tables here")
def test_entry(spark):
    found = __spark_entry__.entry(spark)
    assert found.columns == ["c0", "c1", "c2", "c3", "len", "freq"] and found.count() == 54


@pytest.mark.skipif(not os.path.isdir("/root/testdata/sf0.001"), reason="no given tables here")
@pytest.mark.parametrize("name", ["maximal_itemsets_shards", "compressed_body", "savings_slice_paths_report", "filter_entries", "propagate_fixpoint", "diagram_levels"])
def test_oracles(spark, name):
    duckdb = pytest.importorskip("duckdb")
    data = "/root/testdata/sf0.001"
    c = duckdb.connect()
    for f in os.listdir(data):
        c.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{data}/{f}'")
    got = __spark_entry__.queries()[name](spark, data)
    cols = ", ".join(sorted(got.columns))
    want = c.execute(f"SELECT {cols} FROM ({__spark_entry__.oracle_sql()[name]})").fetchall()

    def plain(rows):
        return sorted(repr([float(v) if isinstance(v, (int, float)) else v for v in r]) for r in rows)

    assert plain(got.select(*sorted(got.columns)).collect()) == plain(want)
