"""A query without keys has one row for an empty join too, as its SQL has."""

from pathlib import Path

import pytest

from ringview.experiments import ORACLES, QUERIES


@pytest.mark.parametrize("name", ["loop4_indicators", "triangle_plain", "triangle_one_symbol", "path_3_total", "sum_nations", "triangle_covariance"])
def test_empty_joins(spark, sf, tmp_path, name):
    import duckdb

    con = duckdb.connect()
    for t in Path(sf).glob("*.parquet"):
        # one line an order, no suppliers: no edges, no tuples of the join
        where = "WHERE l_linenumber = 1" if t.stem == "lineitem" else "LIMIT 0" if t.stem == "supplier" else ""
        con.execute(f"COPY (SELECT * FROM read_parquet('{t}') {where}) TO '{tmp_path}/{t.name}' (FORMAT parquet)")
        con.execute(f"CREATE VIEW {t.stem} AS SELECT * FROM read_parquet('{tmp_path}/{t.name}')")
    want = con.execute(ORACLES[name])
    columns = [c[0] for c in want.description]
    got = [tuple(r) for r in QUERIES[name](spark, str(tmp_path)).select(*columns).collect()]
    assert got == want.fetchall() and len(got) == 1
