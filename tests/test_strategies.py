"""Caps, schemes and cycles in every strategy, loops that settle or raise, measures against plain sums, and the lemma audits."""

import random

import pandas as pd
import pytest
from pyspark.sql import functions as F

from hopbound.functions.search import Csr, search, stream
from hopbound.operators import labels as L
from hopbound.operators import measure as M
from hopbound.operators.audit import TIGHT_CHECKS, lemma_violations
from hopbound.operators.cut import shared_dir
from hopbound.operators.graph import Graph
from hopbound.operators.paths import capped_counts, simple_paths
from hopbound.plans import choose
from hopbound.sources import generators as G
from hopbound.streaming.cycles import closing_cycles, replay


def edges_of(spark, rows):
    return spark.createDataFrame([r[:3] for r in rows], "src bigint, dst bigint, ord int")


def asked(spark, rows):
    return spark.createDataFrame(rows, "instance_id bigint, s bigint, t bigint, k int")


def test_stream_gives_what_search_gives():
    for seed in range(20):
        edges, s, t = G.uniform_digraph(seed, 9)
        csr = Csr.of(edges, (s, t))
        for scheme in ("tight", "guarded", "lazy", "fresh"):
            run = search(csr, csr.index(s), csr.index(t), 5, scheme, cap=40)
            assert [p for p, _ in stream(csr, csr.index(s), csr.index(t), 5, scheme, cap=40)] == run.outputs
    first = next(stream(Csr.of(G.clique_trap(40, True)[0]), 0, 40, 30))
    assert first[0] == (0, 40) and first[1] == 4  # long before the search could end


@pytest.mark.parametrize("strategy", ["task", "split", "relational", "direct", "bidirectional"])
def test_caps_and_cycles_by_strategy(spark, strategy):
    rows, s, _ = G.uniform_digraph(5, 8, 30)
    csr = Csr.of(rows)
    e, q = edges_of(spark, rows).cache(), asked(spark, [(0, s, s, 4), (1, s, (s + 1) % 8, 4)])
    want = {i: [tuple(csr.names[x] for x in p) for p in search(csr, csr.index(s), csr.index(t), 4).outputs] for i, t in ((0, s), (1, (s + 1) % 8))}
    got = simple_paths(e, q, 4, strategy=strategy).select("instance_id", "path").collect()
    assert {i: sorted(tuple(r.path) for r in got if r.instance_id == i) for i in want} == {i: sorted(p) for i, p in want.items()} and len(want[0]) > 3
    if strategy == "bidirectional":
        with pytest.raises(ValueError, match="scan order"):
            simple_paths(e, q, 4, strategy=strategy, cap=2)
    else:
        few = simple_paths(e, q, 4, strategy=strategy, cap=3).select("instance_id", "path")
        assert {(r.instance_id, tuple(r.path)) for r in few.collect()} == {(i, p) for i, ps in want.items() for p in ps[:3]}
        flags = {r.instance_id: (r.outputs, r.capped) for r in capped_counts(few, asked(spark, [(0, 0, 0, 4), (1, 0, 0, 4), (7, 0, 0, 4)]), 3).collect()}
        assert flags == {0: (3, True), 1: (3, True), 7: (0, False)}


def test_planner_keeps_scheme_and_cap(spark, monkeypatch):
    for name in ("MAX_TASK_EDGES", "MANY_EDGES", "DIRECT_ROWS"):
        monkeypatch.setattr(choose, name, 1)
    rows = [(ord(a), ord(b), o) for a, b, o in G.lettered(G.FIG_X)]
    e, q = edges_of(spark, rows), asked(spark, [(0, ord("A"), ord("E"), 4)])
    assert choose.run_planned(e, q, 4).count() == 3
    assert choose.run_planned(e, q, 4, scheme="guarded").count() == 2
    assert choose.run_planned(e, q, 4, cap=1).count() == 1
    with pytest.raises(ValueError, match="lists all paths"):
        simple_paths(e, q, 4, scheme="guarded", strategy="relational")


def test_components_settle_or_raise(spark):
    chain = spark.range(13).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    assert {r.component for r in L.components(chain).collect()} == {0}
    with pytest.raises(RuntimeError, match="settle"):
        L.components(chain, max_rounds=1)
    ring = spark.range(12).select(F.col("id").alias("src"), ((F.col("id") + 1) % 12).alias("dst"))
    assert {r.component for r in L.components(ring, directed=True).collect()} == {0}
    with pytest.raises(RuntimeError, match="settle|end"):
        L.components(ring, directed=True, max_rounds=3)
    both = ring.unionByName(spark.createDataFrame([(3, 50), (50, 51), (60, 2)], "src bigint, dst bigint"))
    assert L.reduce_to_scc(both).count() == 12


def test_measures_are_plain_sums(spark):
    edges, s, t = G.uniform_digraph(3, 9, 45)
    csr = Csr.of(edges)
    rows = []
    for i, (a, b) in enumerate([(0, 1), (2, 3), (4, 5), (6, 7), (1, 8)]):
        rows += M.measure("g", i, csr, a, b, 5, ["tight", "guarded"], 10_000)
    rows += M.measure("g", 99, csr, 0, 8, 5, ["tight", "guarded"], 1)  # capped, so left out
    pdf = pd.DataFrame(rows, columns=[c.split()[0] for c in M.RUN.split(", ")])
    runs = spark.createDataFrame(pdf, M.RUN)
    a, b = (pdf[(pdf.scheme == x) & ~pdf.capped].set_index("instance_id") for x in ("tight", "guarded"))
    steps = lambda x: (x.steps_search + x.steps_cascade + x.steps_output).sum()
    loss = M.loss(runs).first()
    assert (loss.instances, loss.paths, loss.missed, loss.excluded) == (5, a.outputs.sum(), (a.outputs - b.outputs).sum(), 1)
    assert loss.losing_share == round(float((b.outputs < a.outputs).mean()), 4)
    x = M.excess_by_account(runs).first()
    assert x.cascade == round((a.steps_cascade.sum() - b.steps_cascade.sum()) / steps(b), 4) and abs(x.search + x.cascade + x.output - x.net) < 2e-4
    r = M.step_ratio(runs).first()
    assert r.ratio == round((steps(a) / a.intervals.sum()) / (steps(b) / b.intervals.sum()), 4)
    assert r.calls_ratio == round((b.calls.sum() / b.intervals.sum()) / (a.calls.sum() / a.intervals.sum()), 4)
    assert 0 < M.harness_ns(500) < 1e6


def test_missed_paths_and_order(spark):
    whole = spark.createDataFrame([(0, i, p) for i, p in enumerate("abcde")], "graph int, seq int, path_str string")
    part = spark.createDataFrame([(0, i, p) for i, p in enumerate("ace")], "graph int, seq int, path_str string")
    odd = spark.createDataFrame([(0, i, p) for i, p in enumerate("cax")], "graph int, seq int, path_str string")
    assert {r.path_str for r in M.missed(whole, part, ["graph"]).collect()} == {"b", "d"}
    assert tuple(M.order_breaks(whole, part, ["graph"]).first()) == (0, 0) and tuple(M.order_breaks(whole, odd, ["graph"]).first()) == (1, 1)


@pytest.mark.parametrize("seed", range(12))
def test_lemmas_hold_for_the_exact_scheme_alone(seed):
    edges, s, t = G.uniform_digraph(seed + 500, 6 + seed % 3)
    csr = Csr.of(edges, (s, t))
    bad = lemma_violations(csr, csr.index(s), csr.index(t), 3 + seed % 4)
    assert not any(bad[x] for x in TIGHT_CHECKS)


def test_split_node_cycles(spark):
    rows, s, _ = G.uniform_digraph(5, 8, 30)
    g = Graph(edges_of(spark, rows)).split_node(s, 100, 200)
    n = simple_paths(g.edges, asked(spark, [(0, 100, 200, 4)]), 4).count()
    assert n == simple_paths(edges_of(spark, rows), asked(spark, [(0, s, s, 4)]), 4).count() > 0


def test_closing_cycles_of_four_edges_with_expiry(spark):
    hour, draw = 3_600_000_000, random.Random(5)
    rows = [(i, 10 * 24 * hour + i * hour // 12, draw.randrange(9), draw.randrange(9)) for i in range(240)]
    rows = [r for r in rows if r[2] != r[3]]
    edges = spark.createDataFrame(rows, "event_id bigint, at bigint, src bigint, dst bigint").select("event_id", F.timestamp_micros("at").alias("ts"), "src", "dst")
    want = set()
    for e, now, u, v in rows:
        old = {(a, b) for i, at, a, b in rows if now - 2 * hour < at < now}
        walks = [(v,)]
        for _ in range(3):
            walks = [(*w, b) for w in walks for a, b in old if a == w[-1] and b not in w]
            want |= {(e, len(w), ">".join(map(str, (u, *w)))) for w in walks if w[-1] == u}
            walks = [w for w in walks if w[-1] != u]
    sink = f"{shared_dir(spark)}/closing-test"
    closing_cycles(replay(edges, "ts", 4), 4, 2, sink, late_hours=0)
    got = [tuple(r) for r in spark.read.schema("event_id bigint, len bigint, cycle_str string").parquet(f"{sink}/batch=*").collect()]
    assert len(got) == len(set(got)) and set(got) == want and any(n == 4 for _, n, _ in want)
    bins = {r[0] for r in spark.read.parquet(f"{sink}-edges").select("bin").distinct().collect()}
    assert len(bins) == 2 and max(bins) == max(at for _, at, _, _ in rows) // (2 * hour)
