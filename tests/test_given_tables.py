"""Queries whose rows come from the given tables: without these they fail, with them they give what their SQL gives."""

from pathlib import Path

import pytest

from ringview.queries import ORACLES, QUERIES

NAMES = ["operator_union", "operator_join", "operator_marginalize", "operator_negate", "operator_indicator", "factored_products", "measure_view_counts", "classify"]


@pytest.mark.parametrize("name", NAMES)
def test_rows_come_from_the_given_tables(spark, sf, tmp_path, name):
    import duckdb

    with pytest.raises(Exception, match="(?i)path.*not.*exist"):
        QUERIES[name](spark, str(tmp_path)).collect()
    con = duckdb.connect()
    for t in Path(sf).glob("*.parquet"):
        con.execute(f"CREATE VIEW {t.stem} AS SELECT * FROM read_parquet('{t}')")
    want = con.execute(ORACLES[name])
    columns = [c[0] for c in want.description]
    assert sorted(tuple(map(str, r)) for r in QUERIES[name](spark, sf).select(*columns).collect()) == sorted(tuple(map(str, r)) for r in want.fetchall())
