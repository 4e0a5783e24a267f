"""Formulas over the given tables: each agrees with its SQL and is read from a table by Spark."""

import duckdb
import pytest

from rangesieve import catalogue

D = "/root/testdata/sf0.001"
READS = {"goal_matrix": "lineitem", "max_range_lengths": "lineitem", "theory_bpk": "lineitem", "lower_bounds": "lineitem", "theory_memory": "lineitem", "infix_probability": "lineitem", "dyn_bound": "orders", "dyn_duplicates": "orders"}


@pytest.mark.parametrize("name", READS)
def test_formula_reads_its_table(spark, name, monkeypatch):
    read = []
    monkeypatch.setattr(catalogue.k, "table", lambda s, d, t, real=catalogue.k.table: read.append(t) or real(s, d, t))
    found = catalogue.queries()[name](spark, D)
    rows = sorted(map(tuple, found.collect()))
    assert set(read) == {READS[name]}
    con = duckdb.connect()
    for t in ("lineitem", "orders"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{D}/{t}.parquet'")
    want = con.execute(catalogue.oracle_sql()[name])
    assert [c[0] for c in want.description] == found.columns
    near = [tuple(pytest.approx(x, abs=1e-9) if isinstance(x, float) else x for x in r) for r in sorted(want.fetchall())]
    assert rows == near
