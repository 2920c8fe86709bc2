"""Registered queries on tables whose graphs lack the nodes they ask for, or have no path between them."""

import duckdb
import pytest

import __spark_entry__ as entry

NATIONS = [(i, f"NATION{i}", i % 5) for i in range(25)]


@pytest.fixture(scope="module")
def distant(spark, tmp_path_factory):
    """A trade graph of three edges, 3 > 4, 4 > 5 and 9 > 3: nothing leads from 3 to 9, and nodes 7 and 19 are absent."""
    at = str(tmp_path_factory.mktemp("distant"))
    pairs = [(3, 4), (4, 5), (9, 3)]
    made = {
        "nation": (NATIONS, "n_nationkey int, n_name string, n_regionkey int"),
        "customer": ([(i, a) for i, (a, _) in enumerate(pairs)], "c_custkey bigint, c_nationkey int"),
        "supplier": ([(i, b) for i, (_, b) in enumerate(pairs)], "s_suppkey bigint, s_nationkey int"),
        "orders": ([(i, i) for i in range(3)], "o_orderkey bigint, o_custkey bigint"),
        "lineitem": ([(i, i, 1) for i in range(3)], "l_orderkey bigint, l_suppkey bigint, l_linenumber int"),
    }
    con = duckdb.connect()
    for name, (rows, schema) in made.items():
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{at}/{name}.parquet")
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{at}/{name}.parquet/*.parquet'")
    return at, con


def agrees(spark, distant, name):
    at, con = distant
    got = entry.queries()[name](spark, at)
    cols = sorted(got.columns)
    want = con.execute(f"SELECT {', '.join(cols)} FROM ({entry.oracle_sql()[name]}) q").fetchall()
    found = [tuple(r) for r in got.select(*cols).collect()]
    assert sorted(map(str, found)) == sorted(map(str, want)), (name, found, want)
    return found


def test_backtrack_without_its_nodes(spark, distant):
    assert agrees(spark, distant, "backtrack_trade25") == []


def test_circuit_without_its_nodes(spark, distant):
    assert agrees(spark, distant, "circuit_trade50") == []


def test_weighted_paths_without_a_path(spark, distant):
    assert agrees(spark, distant, "weighted_paths_trade") == []


def test_sink_roundtrip_without_a_path(spark, distant):
    assert agrees(spark, distant, "paths_sink_roundtrip") == []


def test_cube_without_a_path(spark, distant):
    assert agrees(spark, distant, "cube_len_src") == [(None, None, 0)]


def test_rollup_without_a_path(spark, distant):
    assert agrees(spark, distant, "rollup_len_trade") == [(None, 0, None)]


def test_simple_paths_counted_without_a_path(spark, distant):
    assert agrees(spark, distant, "udf_is_simple") == [(0, True)]


def test_agreement_of_schemes_without_a_path(spark, distant):
    assert all(r[0] is None and r[1] == 0 for r in agrees(spark, distant, "scheme_agreement_trade"))
