"""The registered queries: names, plans, streams and the smallest data."""

import pytest

import __spark_entry__ as entry
from signpart import tables
from signpart.catalog import graphs, relational, streams
from tests.conftest import DATA


def test_oracles_belong_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry_runs(spark):
    row = entry.entry(spark).collect()
    assert len(row) == 1 and row[0]["n_clusters"] > 0


@pytest.mark.parametrize("name", ["edges_nation", "edges_orders", "sgp_trace_example", "sgp_nation_kernel", "seeded_nation", "op_json", "op_join_asof", "op_planted_source", "udf_table_function", "stream_dedup"])
def test_against_sql(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in ("nation", "region", "customer", "supplier", "orders", "lineitem", "events"):
        con.execute(f"create view {t} as select * from '{DATA}/{t}.parquet'")
    made = {**graphs.QUERIES, **relational.QUERIES, **streams.QUERIES}[name](spark, DATA)
    names = sorted(made.columns)
    want = con.execute(f"select {', '.join(names)} from ({entry.oracle_sql()[name]})").fetchall()
    text = lambda rows: sorted(str(tuple(float(x) if isinstance(x, (int, float)) and not isinstance(x, bool) else x for x in r)) for r in rows)
    assert text(made.select(*names).collect()) == text(want)


def test_filters_and_columns_reach_the_scan(spark):
    plan = relational.QUERIES["op_filter"](spark, DATA)._jdf.queryExecution().toString()
    assert "PushedFilters: [" in plan and "l_comment" not in plan
    scan = next(line for line in plan.splitlines() if "ReadSchema" in line)
    assert "l_tax" not in scan


def test_no_cartesian_product_in_the_partition(spark):
    from signpart import workloads
    from signpart.operators import partition

    edges = tables.written(workloads.places(spark, DATA))
    plan = partition.partition(edges, strategy="kernel").labels._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan


MOVED = ["bad_cycles_example", "cover_missing", "dominant_power_check", "inconsistent_example", "op_edge_list_source", "op_planted_source", "op_recursive"]


@pytest.mark.parametrize("name", MOVED)
def test_reads_a_given_table(spark, monkeypatch, name):
    read, table = set(), tables.table
    monkeypatch.setattr(tables, "table", lambda s, d, t: read.add(t) or table(s, d, t))
    assert entry.queries()[name](spark, DATA).count() > 0 and "lineitem" in read
    monkeypatch.undo()
    test_against_sql(spark, name)


def test_powers_stand_on_both_sides(spark):
    assert {r["dominant"] for r in graphs.QUERIES["dominant_power_check"](spark, DATA).collect()} == {False, True}
