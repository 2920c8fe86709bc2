"""Worst-case families and audits are made of table rows: as many graphs as the rows give."""

import datetime

import duckdb
import pytest

import __spark_entry__ as entry
from hopbound import experiments as X


@pytest.mark.parametrize("name", ["breaker_paths", "breaker_scans", "breaker_hub_entries", "clique_trap_delay", "clique_trap_exit_delay"])
def test_worst_cases_are_dealt_from_customers(spark, tmp_path, name):
    rows = [(i, nation) for i, nation in enumerate([0] * 45 + [1] * 29 + [2] * 40)] + [(None, 0), (900, None)]
    spark.createDataFrame(rows, "c_custkey bigint, c_nationkey int").coalesce(1).write.parquet(f"{tmp_path}/customer.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW customer AS SELECT * FROM '{tmp_path}/customer.parquet/*.parquet'")
    df = entry.queries()[name](spark, str(tmp_path))
    cols = sorted(df.columns)
    got = [tuple(r) for r in df.select(*cols).collect()]
    assert got and sorted(map(str, got)) == sorted(map(str, con.execute(f"SELECT {', '.join(cols)} FROM ({entry.oracle_sql()[name]}) q").fetchall()))
    if name.startswith("breaker"):
        assert {r["k"]: r["graphs"] for r in df.collect()} == {8: 2, 16: 1}  # 45 in twenties; 29 are no thirty; 40 in one of forty


def test_audits_take_a_graph_a_quarter(spark, tmp_path):
    day = datetime.datetime
    pairs = [(day(2001, 1, 5), 0, 3), (day(2001, 2, 5), 3, 0), (day(2001, 3, 5), 0, 3), (day(2001, 1, 7), 1, 4), (day(2001, 5, 1), 0, 6), (day(2001, 5, 1), 0, 7)]
    made = {
        "customer": ([(i, a) for i, (_, a, _) in enumerate(pairs)], "c_custkey bigint, c_nationkey int"),
        "supplier": ([(i, b) for i, (_, _, b) in enumerate(pairs)], "s_suppkey bigint, s_nationkey int"),
        "orders": ([(i, i, d) for i, (d, _, _) in enumerate(pairs)], "o_orderkey bigint, o_custkey bigint, o_orderdate timestamp_ntz"),
        "lineitem": ([(i, i) for i in range(len(pairs))], "l_orderkey bigint, l_suppkey bigint"),
    }
    for name, (rows, schema) in made.items():
        spark.createDataFrame(rows, schema).write.parquet(f"{tmp_path}/{name}.parquet")
    each = X._per_quarter("id long, m long", lambda i, csr: [(i, csr.m)])(spark, str(tmp_path))
    q = 2001 * 4 * 3
    assert {tuple(r) for r in each.collect()} == {(q + 3, 2), (q + 4, 1), (q + 6, 1)}
    got = entry.queries()["audit_lemmas_tight"](spark, str(tmp_path)).collect()
    assert len(got) == len(X.TIGHT_CHECKS) and all(r.violations == 0 for r in got)
