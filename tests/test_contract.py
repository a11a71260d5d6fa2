"""Registered queries run and agree with DuckDB on the smallest tables."""

import os

import pytest

SAMPLE = ["vocab_top", "swa_fences", "exact_hits", "neighbors", "soft_sub", "soft_ins1", "contam_exact", "bm25", "pages_text", "rel_grouping_sets", "win_sessions"]


def canon(df):
    rows = []
    for r in df[sorted(df.columns)].itertuples(index=False):
        rows.append(tuple("None" if v is None or v != v else f"{v:.6f}" if isinstance(v, float) else str(v) for v in r))
    return sorted(rows)


@pytest.mark.parametrize("name", SAMPLE)
def test_query_matches_oracle(spark, sf, name):
    import duckdb

    from ngramlake.plans import registry

    con = duckdb.connect()
    for t in os.listdir(sf):
        con.sql(f"create view {t.removesuffix('.parquet')} as select * from '{sf}/{t}'")
    got, want = registry.QUERIES[name](spark, sf).toPandas(), con.sql(registry.ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert canon(got) == canon(want)


def test_entry_imports():
    import __spark_entry__ as e

    assert "soft_sub" in e.queries() and set(e.oracle_sql()) <= set(e.queries())


def test_neighbours_are_broadcast(spark, sf):
    from ngramlake.plans import registry

    plan = registry.QUERIES["soft_sub"](spark, sf)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan


def test_every_statement_reads_a_table():
    from ngramlake.plans import relational

    for name, made in relational.STATEMENTS.items():
        for statement in (made,) if isinstance(made, str) else made:
            assert relational._tables(statement), name
