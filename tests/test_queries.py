"""Registered queries against their SQL at the smallest size, and the shape of the workloads."""

import duckdb
import pytest

from eigenveil.plans import catalogue, workloads
from verify import rows_of

HEAVY = {"gram_matrix", "subspace_equal", "encrypted_match"}


@pytest.fixture(scope="module")
def duck(sf):
    from pathlib import Path

    con = duckdb.connect()
    for path in Path(sf).glob("*.parquet"):
        con.execute(f"CREATE VIEW {path.stem} AS SELECT * FROM read_parquet('{path}')")
    return con


@pytest.mark.parametrize("name", sorted(set(catalogue.SQL) - HEAVY))
def test_query_equals_sql(spark, sf, duck, name):
    got = catalogue.QUERIES[name](spark, sf).toPandas()
    want = duck.execute(catalogue.SQL[name])
    columns = [d[0] for d in want.description]
    assert sorted(got.columns) == sorted(columns)
    assert rows_of(list(got.columns), got.astype(object).where(got.notna(), None).itertuples(index=False, name=None)) == rows_of(columns, want.fetchall())


def test_accuracy_rises_with_the_budget(spark):
    rows = workloads.w5_eps_sweep(spark, "/root/testdata/sf0.01").collect()
    for name in ("network", "centroid"):
        curve = {r.eps: r.f1 for r in rows if r.recogniser == name}
        assert len(curve) == 10 and curve[8.0] >= 0.85 and curve[4.0] >= 0.6 and curve[0.5] <= 0.55 and curve[None] >= curve[8.0] - 0.03, (name, curve)


def test_null_control_stays_at_chance(spark, sf):
    assert all(abs(r.f1 - 0.1) <= 0.08 for r in workloads.w5_null_control(spark, sf).collect())
