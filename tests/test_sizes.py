"""What lets registered queries grow: results that do not pass through the driver, counts instead of lists, and few rounds."""

import random

import numpy as np
from pyspark.sql import functions as F

import __spark_entry__ as entry
from hopbound.operators import labels as L
from hopbound.operators import paths as P
from hopbound.operators.chains import chains_from, two_hop_chains
from hopbound.operators.paths import all_cycles
from hopbound.streaming.cycles import replay, run_to_table


def test_streams_do_not_gather_their_output_on_the_driver(spark):
    df = spark.range(40).selectExpr("id", "timestamp_micros(id * 1000000) AS ts")
    for mode, stream in (("append", replay(df, "ts", 3)), ("complete", replay(df, "ts", 3).groupBy("id").count())):
        out = run_to_table(stream, mode)
        assert sorted(r.id for r in out.collect()) == list(range(40))
        assert "Memory" not in out._jdf.queryExecution().optimizedPlan().toString()


def _brute(rows, wide):
    out = {}
    for t, a in rows:
        for t2, b in rows:
            if t < t2 <= t + wide and b != a:
                for t3, c in rows:
                    if t2 < t3 <= t2 + wide and c not in (a, b):
                        out[a] = out.get(a, 0) + 1
    return out


def test_chains_are_those_of_a_plain_search(spark):
    for seed in range(30):
        r = random.Random(seed)
        rows = [(r.randrange(60), r.randrange(4)) for _ in range(40)]
        at, user = (np.array(x) for x in zip(*rows))
        found, got = chains_from(at, user, np.ones(len(rows), bool), 7), {}
        for u, n in zip(user.tolist(), found.tolist()):
            got[u] = got.get(u, 0) + n
        assert {u: n for u, n in got.items() if n} == _brute(rows, 7), seed
    rows = [(r.randrange(-90, 90), r.randrange(5)) for _ in range(80)] + [(None, 1), (3, None)]
    df = spark.createDataFrame(rows, "at bigint, user_id bigint")
    assert {x.a: x.paths for x in two_hop_chains(df, 7).collect()} == _brute([x for x in rows if None not in x], 7)


def test_chains_are_not_listed():
    n = 20_000  # some 10^12 chains
    at, user = np.arange(n), np.arange(n)
    i = np.arange(n, dtype=object)
    assert chains_from(at, user, np.ones(n, bool), n).tolist() == [(n - 1 - x) * (n - 2 - x) // 2 for x in i]


def test_long_rising_chains_settle_in_few_rounds(spark):
    rise = spark.range(3000).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    assert L.components(rise, directed=True, max_rounds=5).where("id <> component").count() == 0
    ring = spark.createDataFrame([(10, 7), (7, 12), (12, 10), (4, 4)], "src bigint, dst bigint")
    got = {r.id: r.component for r in L.components(rise.where("src < 7 OR src > 12").unionByName(ring), directed=True, max_rounds=9).collect()}
    assert {i for i, c in got.items() if c != i} == {10, 12} and got[10] == got[12] == 7


def test_cycles_inside_components_of_a_long_chain_take_few_rounds(spark, monkeypatch):
    rounds = []
    cut = L.cut
    monkeypatch.setattr(L, "cut", lambda df: rounds.append(1) or cut(df))
    rise = spark.range(120).selectExpr("id AS src", "id + 1 AS dst", "CAST(1 AS INT) AS ord")
    assert L.reduce_to_scc(rise).count() == 0 and len(rounds) < 15


def _plain_cycles(edges, k, walk):
    if len(walk) > 1 and walk[-1] == walk[0]:
        return [(walk[0], len(walk) - 1, walk)]
    steps = [b for a, b in edges if a == walk[-1] and (b == walk[0] or b > walk[0] and b not in walk)] if len(walk) <= k else []
    return [c for b in steps for c in _plain_cycles(edges, k, (*walk, b))]


def test_cycles_from_hubs_are_those_of_a_plain_search(spark):
    for seed, (n, m, k) in enumerate([(8, 30, 3), (8, 30, 4), (6, 20, 6)]):
        r = random.Random(seed)
        edges = {(f"n{r.randrange(n)}", f"n{r.randrange(n)}") for _ in range(m)} | {("n0", f"n{i}") for i in range(1, n)}
        edges = sorted((a, b) for a, b in edges if a != b)
        found = all_cycles(spark.createDataFrame([(*e, 1) for e in edges], "src string, dst string, ord int"), k, strategy="hubs")
        want = [c for x in sorted({a for a, _ in edges}) for c in _plain_cycles(edges, k, (x,))]
        assert sorted((r.root, r.len, tuple(r.path)) for r in found.collect()) == sorted(want), (n, m, k)
    assert not all_cycles(spark.createDataFrame([], "src bigint, dst bigint, ord int"), 4, strategy="hubs").collect()


def test_cycles_from_hubs_leave_in_an_order_that_files_compress(spark, tmp_path):
    users = random.Random(3).sample(range(5000), 300)
    edges = [(a, b, 1) for u in users for i in (90001, 90002) for a, b in ((u, i), (i, u))]
    found = all_cycles(spark.createDataFrame(edges, "src bigint, dst bigint, ord int"), 4, strategy="hubs").where("len = 4").select("path")
    found.coalesce(1).write.parquet(f"{tmp_path}/found")
    rows = [tuple(r.path) for r in spark.read.parquet(f"{tmp_path}/found").collect()]
    assert len(rows) == len(set(rows)) == 300 * 299
    # neighbours differ in one user but for the ends of the runs of a first user
    assert sum(a[:2] == b[:2] and a[2] < b[2] for a, b in zip(rows, rows[1:])) > 0.97 * len(rows)


def test_cycles_from_hubs_of_several_blocks(spark, monkeypatch):
    monkeypatch.setattr(P, "HALVES_OF_A_BLOCK", 3)
    r = random.Random(5)
    edges = sorted({(a, b) for a, b in ((r.randrange(10), r.randrange(10)) for _ in range(60)) if a != b} | {(a, b) for i in range(9) for a, b in ((9, i), (i, 9), (5, i)) if a != b})
    found = all_cycles(spark.createDataFrame([(*e, 1) for e in edges], "src bigint, dst bigint, ord int"), 5, strategy="hubs")
    assert sorted((x.root, x.len, tuple(x.path)) for x in found.collect()) == sorted(c for x in range(10) for c in _plain_cycles(edges, 5, (x,)))


def test_cycles_of_bigrams_need_no_search(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(P, "search_groups", None)
    spark.createDataFrame([(1, "b c a b c a b c a b a b", "en")], "doc_id bigint, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    got = entry.queries()["cycles_all_bigrams"](spark, str(tmp_path)).collect()
    assert [tuple(r) for r in got] == [(3, "a>b>c>a")]


def test_cycles_of_users_and_items_need_no_search(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(P, "search_groups", None)
    rows = [(1, "click", 7), (2, "purchase", 7), (2, "click", 8), (1, "purchase", 8), (3, "click", 8), (3, "purchase", 8), (4, "view", 7)]
    events = spark.createDataFrame([(u, kind, f'{{"k": {k}}}') for u, kind, k in rows], "user_id bigint, event_type string, props string")
    events.write.parquet(f"{tmp_path}/events.parquet")
    got = entry.queries()["cycles_all_useritem"](spark, str(tmp_path)).collect()
    assert sorted(tuple(r) for r in got) == [(2, "3>1000008>3"), (4, "1>1000007>2>1000008>1")]


def test_paths_between_hub_words_need_no_search(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(P, "search_groups", None)
    text = " ".join(3 * ["the a of b the c d of"])
    spark.createDataFrame([(1, text, "en")], "doc_id bigint, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    got = entry.queries()["paths_bigrams"](spark, str(tmp_path)).collect()
    assert sorted(tuple(r) for r in got) == [(2, "the>a>of"), (3, "the>c>d>of")]
