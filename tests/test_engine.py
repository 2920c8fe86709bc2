"""Strategies, reductions, sources and streams on Spark, on small graphs."""

import random
import re
from pathlib import Path

import duckdb
import pytest
from pyspark.sql import functions as F

from hopbound.functions.search import COMPLETE, Csr, search
from hopbound.operators import labels as L
from hopbound.operators import measure as M
from hopbound.operators.audit import audit_outputs, write_chains
from hopbound.operators.graph import Graph
from hopbound.operators.paths import STRATEGIES, all_cycles, simple_paths
from hopbound.plans.choose import choose, run_planned
from hopbound.sources import generators as G
from hopbound.sources.datasource import adjacency, generated, read_edges, write_paths
from hopbound.sources.tables import TABLES

DATA = "/root/testdata/sf0.001"
QUERY = "instance_id bigint, s bigint, t bigint, k int"


def edges_of(spark, rows):
    return Graph(spark.createDataFrame(rows, "src bigint, dst bigint")).simplify().ordered().edges


@pytest.fixture(scope="module")
def small(spark):
    r = random.Random(4)
    rows = [(a, b) for a in range(12) for b in r.sample(range(12), 4)]
    return rows, edges_of(spark, rows).cache()


@pytest.mark.parametrize("strategy", [*STRATEGIES, "auto"])
def test_strategies_agree(spark, small, strategy):
    rows, e = small
    asked = [(1, 0, 5, 4), (2, 3, 7, 3), (3, 5, 0, 1)]
    csr = Csr.of(rows)
    want = {(i, tuple(csr.names[x] for x in p)) for i, s, t, k in asked for p in search(csr, csr.index(s), csr.index(t), k).outputs}
    got = simple_paths(e, spark.createDataFrame(asked, QUERY), 4, strategy=strategy).select("instance_id", "path").collect()
    assert len(got) == len(want) and {(r[0], tuple(r[1])) for r in got} == want


@pytest.mark.parametrize("scheme", COMPLETE)
def test_cycles_through_a_node_and_by_split(spark, small, scheme):
    rows, e = small
    csr = Csr.of(rows)
    want = {tuple(csr.names[x] for x in p) for p in search(csr, csr.index(2), csr.index(2), 4).outputs}
    got = simple_paths(e, spark.createDataFrame([(0, 2, 2, 4)], QUERY), 4, scheme=scheme)
    assert {tuple(r.path) for r in got.collect()} == want
    if scheme == "tight":
        cut = Graph(e).split_node(2, 102, 202).edges
        other = simple_paths(cut, spark.createDataFrame([(0, 102, 202, 4)], QUERY), 4).collect()
        assert {tuple(2 if x > 100 else x for x in r.path) for r in other} == want


def test_all_cycles_once(spark, small):
    rows, e = small
    csr = Csr.of(rows)
    want = set()
    for s in range(csr.n):
        for p in search(csr, s, s, 4).outputs:
            ring = [csr.names[x] for x in p[:-1]]
            i = ring.index(min(ring))
            want.add((*ring[i:], *ring[:i], ring[i]))
    for strategy in ("joins", "shipped", "auto"):
        got = [tuple(r.path) for r in all_cycles(e, 4, strategy=strategy).collect()]
        assert len(got) == len(set(got)) and set(got) == want


def test_absent_nodes_empty_graph_and_strings(spark):
    e = edges_of(spark, [(1, 2), (2, 3)])
    q = spark.createDataFrame([(0, 9, 2, 3), (1, 3, 1, 3)], QUERY)
    assert simple_paths(e, q, 3).count() == 0
    none = e.where("src < 0")
    assert simple_paths(none, q, 3).count() == 0 and all_cycles(none, 3).count() == 0 and all_cycles(none, 3, strategy="shipped").count() == 0
    assert run_planned(none, q, 3).count() == 0
    words = Graph(spark.createDataFrame([("ä", "b"), ("b", "ä"), ("b", "c"), ("c", None)], "src string, dst string")).simplify().ordered().edges
    assert [r.path for r in all_cycles(words, 3).collect()] == [["b", "ä", "b"]]


def test_reduction_keeps_every_path_and_drops_the_rest(spark, small):
    rows, e = small
    q = spark.createDataFrame([(0, 0, 5, 3)], QUERY)
    kept = {(r.src, r.dst) for r in L.budget_subgraph(e, q, 3).collect()}
    csr = Csr.of(rows)
    used = {x for p in search(csr, csr.index(0), csr.index(5), 3).outputs for x in zip((csr.names[i] for i in p), (csr.names[i] for i in p[1:]))}
    assert used <= kept < {(a, b) for a, b in rows if a != b}
    assert choose(L.budget_subgraph(e, q, 3)).strategy == "task"


def test_components(spark):
    e = edges_of(spark, [(1, 2), (2, 3), (3, 1), (3, 4), (4, 5), (5, 4), (6, 5)])
    got = {r.id: r.component for r in L.components(e, directed=True).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 4: 4, 5: 4, 6: 6}
    assert {r.component for r in L.components(e).collect()} == {1}


def test_audits_of_outputs_and_writes(spark, small):
    _, e = small
    q = spark.createDataFrame([(0, 0, 5, 4)], QUERY)
    good = simple_paths(e, q, 4)
    assert sum(audit_outputs(good, e, q).first()) == 0
    bad = spark.createDataFrame([(0, 2, [0, 0, 5])], "instance_id bigint, len int, path array<bigint>")
    assert sum(audit_outputs(bad, e, q).first()) > 0
    w = spark.createDataFrame([(1, 7, "raise"), (2, 7, "raise"), (3, 7, "drop")], "seq bigint, node bigint, kind string")
    assert {r.kind: r.longest for r in write_chains(w).collect()} == {"raise": 2, "drop": 1}


def test_measures_reproduce_loss_and_bounds(spark):
    rows = spark.range(24).select(F.col("id").alias("instance_id"), F.lit(6).alias("k"))
    runs = M.measure_generated(rows, lambda i, k: G.uniform_digraph(i), "dense", ["tight", "guarded"], 5000).cache()
    assert sum(M.bound_violations(runs).first()) == 0
    loss = M.loss(runs).first()
    assert 0 < loss.loss < 0.5 and loss.losing_share > 0
    assert M.step_ratio(runs).first().ratio > 1
    x = M.excess_by_account(runs).first()
    assert x.cascade > abs(x.search)
    assert M.delays(runs).count() == 2 and M.wallclock_ratio(runs).first().wall_ratio > 0


def test_sources_and_sinks(spark, tmp_path):
    lines = spark.createDataFrame([("1 2 3",), ("2",), (" 3 1 ",)], "value string")
    assert sorted(tuple(r) for r in adjacency(lines).collect()) == [(1, 2, 1), (1, 3, 2), (3, 1, 1)]
    e = edges_of(spark, [(1, 2), (2, 3)])
    for fmt in ("parquet", "orc", "json", "csv"):
        at = str(tmp_path / fmt)
        e.select("src", "dst").write.format(fmt).option("header", "true").save(at)
        assert read_edges(spark, at, fmt, schema="src bigint, dst bigint").count() == 2
    write_paths(spark.createDataFrame([(1, [1, 2])], "len int, path array<bigint>"), str(tmp_path / "p"))
    assert spark.read.parquet(str(tmp_path / "p")).first().path_str == "1>2"
    assert generated(spark, "clique_trap", 5, 2).groupBy("instance_id").count().count() == 2


def test_registered_queries_match_duckdb(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    queries, oracles = entry.queries(), entry.oracle_sql()
    assert set(oracles) <= set(queries) and len(queries) > 100
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    for name in ("paths_trade100", "cycles_all_payflow", "temporal_paths_payflow", "graph_bigrams", "fig_x_interval_steps", "stream_tumbling_edges", "scc_navlinks"):
        df = queries[name](spark, DATA)
        cols = sorted(df.columns)
        want = con.execute(f"SELECT {', '.join(cols)} FROM ({oracles[name]}) q").fetchall()
        got = [tuple(r) for r in df.select(*cols).collect()]
        assert sorted(map(str, got)) == sorted(map(str, want)), name


def test_scans_are_pruned(spark):
    from hopbound.sources.tables import graph

    plan = graph(spark, DATA, "payflow").edges._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    schemas = re.findall(r"ReadSchema: (.*)", plan)
    assert schemas and all("props" not in s and "value" not in s for s in schemas)
    assert "EqualTo(event_type,purchase)" in plan


def test_library_collects_only_bounded_things():
    root = Path(__file__).resolve().parents[1] / "hopbound"
    for f in [*(root / "operators").glob("*.py"), *(root / "streaming").glob("*.py"), *(root / "plans").glob("*.py")]:
        for line in f.read_text().splitlines():
            assert ".collect()" not in line or "limit(" in line, (f, line)
            assert "localCheckpoint" not in line and ".rdd" not in line, (f, line)


def test_bigrams_are_of_texts_of_any_length(spark, tmp_path):
    from hopbound.sources.tables import graph

    rows = [(1, "left right " * 500, "en", 5500), (2, "links rechts " * 500, "de", 6500), (3, "up down up down up down", "en", 23)]
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, n_chars bigint").write.parquet(f"{tmp_path}/documents.parquet")
    got = {(r.src, r.dst): r.w for r in graph(spark, str(tmp_path), "bigrams").edges.collect()}
    assert got == {("left", "right"): 500, ("right", "left"): 499, ("up", "down"): 3}
