"""Every query with a SQL twin gives the same rows in Spark and in DuckDB."""

import duckdb
import pytest

from treesketch.experiments.oracles import oracle_sql
from treesketch.experiments.queries import queries
from treesketch.sources.tables import TABLES

SQL, QUERIES = oracle_sql(), queries()


@pytest.fixture(scope="module")
def db(tiny):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{tiny}/{t}.parquet'")
    return con


def test_every_query_has_a_twin():
    assert set(SQL) == set(QUERIES)


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_same_rows(spark, db, tiny, name):
    df = QUERIES[name](spark, tiny)
    want = db.sql(SQL[name])
    columns = sorted(want.columns)
    assert sorted(df.columns) == columns
    at = [want.columns.index(c) for c in columns]
    assert sorted(repr(tuple(r[c] for c in columns)) for r in df.collect()) == sorted(repr(tuple(r[i] for i in at)) for r in want.fetchall())


@pytest.mark.parametrize("name", ["compression_ratio", "cost_grid", "cost_speedup", "ledger_rollup", "literal_stride_coverage", "sketch_sizes", "speedup_table", "tree_edges", "tree_ledger", "warmup_schedule"])
def test_closed_forms_take_their_sizes_from_a_table(spark, tiny, name):
    assert QUERIES[name](spark, tiny).inputFiles()
