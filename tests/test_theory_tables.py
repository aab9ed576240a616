"""The closed forms are taken for sizes counted in a given table, which Spark reads."""

import duckdb
import pytest

from hybridrange import registry


@pytest.mark.parametrize("name", ["space_model", "in_range_fraction", "printed_fraction_bounds"])
def test_sizes_come_from_the_line_items(spark, sf_dir, name):
    df = registry.queries()[name](spark, sf_dir)
    assert any("lineitem" in x for x in df.inputFiles())
    span = "month" if name == "space_model" else "day"
    sizes = {n for (n,) in duckdb.connect().sql(f"SELECT DISTINCT count(*) FROM read_parquet('{sf_dir}/lineitem.parquet') GROUP BY date_trunc('{span}', l_shipdate)").fetchall()}
    assert {(r.o, r.n) for r in df.collect()} == {(o, n) for o in (2, 4, 16) for n in sizes}


@pytest.mark.parametrize("name", ["space_model", "in_range_fraction"])
def test_closed_forms_against_sql(spark, sf_dir, name):
    con, df = duckdb.connect(), registry.queries()[name](spark, sf_dir)
    con.sql(f"CREATE VIEW lineitem AS SELECT * FROM read_parquet('{sf_dir}/lineitem.parquet')")
    want = con.sql(f"SELECT {', '.join(df.columns)} FROM ({registry.oracles()[name]})").fetchall()
    assert sorted(map(tuple, df.collect())) == sorted(want)


def test_bounds_are_for_two_rows_and_more(spark, sf_dir):
    rows = registry.queries()["printed_fraction_bounds"](spark, sf_dir).collect()
    assert any(r.n < 2 for r in rows) and all((r.low is None) == (r.n < 2) for r in rows)
