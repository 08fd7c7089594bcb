"""A few registered queries against their SQL, and that every one with SQL has a query."""

import duckdb
import pytest

import __spark_entry__ as entry

D = "/root/testdata/sf0.001"
SOME = ["chain_depth4_event_chain", "remote_customer_totals", "components_doc_overlap", "list_rank_turn_chain", "msf_supplier_mesh", "pagerank_page_links", "preorder_geo_forest", "join_range_events", "window_range", "udf_pandas_scalar", "stream_running_rank"]


@pytest.fixture(scope="session")
def duck():
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{D}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", SOME)
def test_same_as_sql(spark, duck, name):
    df = entry.queries()[name](spark, D)
    cols = sorted(df.columns)
    a = sorted((tuple(r) for r in df.select(cols).collect()), key=repr)
    r = duck.sql(entry.oracle_sql()[name])
    assert sorted(r.columns) == cols
    b = sorted((tuple(x[r.columns.index(c)] for c in cols) for x in r.fetchall()), key=repr)
    if name.startswith("pagerank"):
        assert all(x[0] == y[0] and abs(x[1] - y[1]) < 1e-8 for x, y in zip(a, b)) and len(a) == len(b)
    else:
        assert a == b


def test_entry_and_registry(spark):
    assert entry.entry(spark).count() == 1000
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_rounds_of_read_plans_come_from_a_table(spark, duck):
    """Numbers of orders that customers have, not a range made up."""
    df = entry.queries()["read_plan_rounds"](spark, D)
    assert any(f.endswith("orders.parquet") for f in df.inputFiles())
    want = duck.sql(entry.oracle_sql()["read_plan_rounds"])
    assert sorted(map(tuple, df.select(want.columns).collect())) == sorted(want.fetchall())


def test_every_query_reads_a_table():
    assert "program_sizes" not in entry.queries()
