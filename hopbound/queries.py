"""The registered queries over the relational tables, and SQL for DuckDB that gives the same rows.

SQL is left out where results are not expressible there (step counts of searches, incomplete schemes).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hopbound import experiments as X
from hopbound.functions import sqlapi
from hopbound.functions.search import COMPLETE
from hopbound.operators import chains
from hopbound.operators import labels as L
from hopbound.operators.cut import cut
from hopbound.operators.graph import Graph
from hopbound.operators.paths import all_cycles, capped_counts, path_string, recursive_sql, simple_paths, walk_upper_bound
from hopbound.plans.choose import run_planned
from hopbound.sources import datasource
from hopbound.sources.generators import FIG_X, FIG_Y, lettered
from hopbound.sources.tables import GRAPHS, duck, graph, micros, oracle, sql, table
from hopbound.streaming import cycles as stream

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

# graph, s, t, k of the path workloads
PATHS = {
    "payflow": (8, 46, 4), "trade100": (3, 9, 4), "partchain": (1, 2, 6), "custchain": (1, 2, 4), "useritem": (8, 46, 4), "knn": (384, 95, 6),
    "bigrams": ("the", "of", 3), "navlinks": ("/de", "/Asraes", 8), "schema": ("N0", "S42", 4), "turns": ("the.", "as", 5), "supplychain": (0, 1, 3),
}


def lit(x) -> str:
    return f"'{x}'" if isinstance(x, str) else f"CAST({x} AS BIGINT)"


def asked(spark: SparkSession, rows: list[tuple], like: DataFrame | str) -> DataFrame:
    node = like if isinstance(like, str) else like.schema["src"].dataType.simpleString()
    return spark.createDataFrame(rows, f"instance_id bigint, s {node}, t {node}, k int")


def shown(paths: DataFrame, *more: str) -> DataFrame:
    return paths.select(*more, F.col("len").cast("long").alias("len"), path_string().alias("path_str"))


def walks(edges: str, s, t, k: int) -> str:
    """DuckDB: w(tail, path, len) of one query; its complete rows have tail = t and len > 0."""
    return (
        f"WITH RECURSIVE e AS ({edges}), w(tail, path, len) AS (SELECT {lit(s)}, [{lit(s)}], 0 UNION ALL SELECT e.dst, list_append(w.path, e.dst), w.len + 1 FROM w JOIN e ON e.src = w.tail "
        f"WHERE w.len < {k} AND (w.len = 0 OR w.tail <> {lit(t)}) AND (e.dst = {lit(t)} OR NOT list_contains(w.path, e.dst)))"
    )


STR = "array_to_string(path, '>') AS path_str"


def found(edges: str, s, t, k: int, columns: str = f"CAST(len AS BIGINT) AS len, {STR}") -> str:
    return f"{walks(edges, s, t, k)} SELECT {columns} FROM w WHERE tail = {lit(t)} AND len > 0"


def cycle_walks(edges: str, k: int) -> str:
    return (
        f"WITH RECURSIVE e AS ({edges}), w(root, tail, path, len) AS (SELECT DISTINCT src, src, [src], 0 FROM e UNION ALL SELECT w.root, e.dst, list_append(w.path, e.dst), w.len + 1 FROM w JOIN e ON e.src = w.tail "
        f"WHERE w.len < {k} AND (w.len = 0 OR w.tail <> w.root) AND (e.dst = w.root OR (e.dst > w.root AND NOT list_contains(w.path, e.dst))))"
    )


def add(name: str, query: Query, sql_text: str | None = None) -> None:
    QUERIES[name] = query
    if sql_text:
        ORACLES[name] = duck(sql_text)


def _paths(g: str, s, t, k: int, **how) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        e = cut(graph(spark, d, g).edges)
        return shown(simple_paths(e, asked(spark, [(0, s, t, k)], e), k, **how))

    return run


for g, (s, t, k) in PATHS.items():
    add(f"paths_{g}", _paths(g, s, t, k, strategy="relational") if g == "bigrams" else _paths(g, s, t, k), found(oracle(g), s, t, k))  # between hubs most edges are on a path, too many for one task

# the flagship on the smallest tables, where users 0 to 14 buy
add("paths_payflow_small", _paths("payflow", 1, 2, 4), found(oracle("payflow"), 1, 2, 4))
_PAY = (8, 46, 4)
for scheme in COMPLETE:
    if scheme != "tight":
        name = "seeded" if scheme == "tight_seeded" else scheme
        add(f"scheme_{name}_payflow", _paths("payflow", 8, 46, 3, scheme=scheme), found(oracle("payflow"), 8, 46, 3))
for strategy in ("split", "relational", "bidirectional"):
    add(f"strategy_{strategy}_payflow", _paths("payflow", *_PAY, strategy=strategy), found(oracle("payflow"), *_PAY))
add("strategy_planned_payflow", lambda spark, d: shown(run_planned(e := cut(graph(spark, d, "payflow").edges), asked(spark, [(0, *_PAY)], e), 4)), found(oracle("payflow"), *_PAY))
for scheme in ("guarded", "lazy_tight"):
    add(f"{scheme}_payflow", _paths("payflow", *_PAY, scheme=scheme))


def _recursive(spark: SparkSession, d: str) -> DataFrame:
    e = cut(graph(spark, d, "payflow").edges.select("src", "dst"))
    e.createOrReplaceTempView("hopbound_edges")
    return shown(spark.sql(recursive_sql("hopbound_edges", "CAST(8 AS BIGINT)", "CAST(46 AS BIGINT)", 4)))


add("strategy_recursive_sql_payflow", _recursive, found(oracle("payflow"), *_PAY))
add("recursive_paths_trade", lambda spark, d: _recursive_trade(spark, d), found(oracle("trade100"), 3, 9, 3))


def _recursive_trade(spark: SparkSession, d: str) -> DataFrame:
    e = cut(graph(spark, d, "trade100").edges.select("src", "dst"))
    e.createOrReplaceTempView("hopbound_trade")
    return shown(spark.sql(recursive_sql("hopbound_trade", "CAST(3 AS BIGINT)", "CAST(9 AS BIGINT)", 3)))


# --- several graphs or queries at once -------------------------------------------------------------

SWEEP = {25: (19, 9), 50: (7, 9), 100: (3, 9), 200: (2, 9), 400: (13, 19)}


def _sweep(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for m, (s, t) in SWEEP.items():
        e = cut(graph(spark, d, f"trade{m}").edges)
        one = shown(simple_paths(e, asked(spark, [(m, s, t, 3)], e), 3).withColumnRenamed("instance_id", "m"), "m")
        out = one if out is None else out.unionByName(one)
    return out


add("paths_trade_sweep", _sweep, " UNION ALL ".join(f"SELECT * FROM ({found(oracle(f'trade{m}'), s, t, 3, f'CAST({m} AS BIGINT) AS m, CAST(len AS BIGINT) AS len, {STR}')}) x{m}" for m, (s, t) in SWEEP.items()))


def _pairs(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    g = graph(spark, d, "trade100")
    e = cut(g.edges)
    n = Graph(e).nodes
    a, b = n.select(F.col("id").alias("s")), n.select(F.col("id").alias("t"))
    return e, a.join(b, F.col("s") != F.col("t")).select((F.col("s") * 1000 + F.col("t")).alias("instance_id"), "s", "t", F.lit(3).alias("k"))


def _multi_pairs(spark: SparkSession, d: str) -> DataFrame:
    e, q = _pairs(spark, d)
    found_ = simple_paths(e, cut(q), 3)
    return found_.groupBy(F.element_at("path", 1).alias("s"), F.element_at("path", -1).alias("t")).agg(F.count(F.lit(1)).alias("paths"), F.min("len").cast("long").alias("shortest"))


_ALL_PAIRS = f"WITH RECURSIVE e AS ({oracle('trade100')}), w(s, tail, path, len) AS (SELECT DISTINCT src, src, [src], 0 FROM e UNION ALL SELECT w.s, e.dst, list_append(w.path, e.dst), w.len + 1 FROM w JOIN e ON e.src = w.tail WHERE w.len < 3 AND NOT list_contains(w.path, e.dst))"
add("paths_multi_pairs_trade", _multi_pairs, f"{_ALL_PAIRS} SELECT s, tail AS t, count(*) AS paths, CAST(min(len) AS BIGINT) AS shortest FROM w WHERE len > 0 GROUP BY s, tail")
add("shortest_per_pair", lambda spark, d: _shortest_per_pair(spark, d), f"{_ALL_PAIRS} SELECT s, t, path_str FROM (SELECT s, tail AS t, {STR}, row_number() OVER (PARTITION BY s, tail ORDER BY len, path) AS r FROM w WHERE len > 0) x WHERE r = 1")


def _shortest_per_pair(spark: SparkSession, d: str) -> DataFrame:
    e, q = _pairs(spark, d)
    w = Window.partitionBy("instance_id").orderBy("len", "path")
    top = simple_paths(e, cut(q), 3).withColumn("r", F.row_number().over(w)).where("r = 1")
    return top.select(F.element_at("path", 1).alias("s"), F.element_at("path", -1).alias("t"), path_string().alias("path_str"))


add("paths_seq_order_trade", lambda spark, d: _seq(spark, d), found(oracle("trade100"), 3, 9, 4, f"row_number() OVER (ORDER BY path) AS seq, {STR}"))


def _seq(spark: SparkSession, d: str) -> DataFrame:
    e = cut(graph(spark, d, "trade100").edges)
    return simple_paths(e, asked(spark, [(0, 3, 9, 4)], e), 4).select("seq", path_string().alias("path_str"))


add("lexi_first10", lambda spark, d: _seq(spark, d).orderBy("seq").limit(10), f"SELECT * FROM ({ORACLES['paths_seq_order_trade']}) x WHERE seq <= 10")


def _agreement(spark: SparkSession, d: str) -> DataFrame:
    e = cut(graph(spark, d, "trade100").edges)
    out = None
    for scheme in COMPLETE:
        one = simple_paths(e, asked(spark, [(0, 3, 9, 4)], e), 4, scheme=scheme)
        one = one.agg(F.lit(scheme).alias("scheme"), F.count(F.lit(1)).alias("paths"), F.md5(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("seq", path_string().alias("p")))), lambda x: x["p"]), ";")).alias("digest"))
        one = one.withColumn("digest", F.when(F.col("paths") > 0, F.col("digest")))
        out = one if out is None else out.unionByName(one)
    return out


add("scheme_agreement_trade", _agreement, f"SELECT scheme, paths, digest FROM (SELECT count(*) AS paths, md5(string_agg(path_str, ';' ORDER BY seq)) AS digest FROM ({ORACLES['paths_seq_order_trade']}) y) x CROSS JOIN (VALUES {', '.join(f'({lit(s)})' for s in COMPLETE)}) v(scheme)")

# node predicate: good, non-toxic documents only
_QUALITY = "SELECT doc_id AS id FROM {labels} GROUP BY doc_id HAVING min(quality) = 1 AND max(toxic) = 0"
_NOT_BAD = "SELECT doc_id AS id FROM {labels} WHERE quality = 0 OR toxic = 1"


def _doclines(spark: SparkSession, d: str) -> DataFrame:
    g = graph(spark, d, "doclines")
    bad = sql(spark, d, _NOT_BAD).distinct()
    e = cut(g.induced(g.nodes.join(bad, "id", "left_anti")).edges)
    starts = e.groupBy("src").count().orderBy(F.desc("count"), "src").limit(3).select(F.col("src").alias("s"))
    ends = e.groupBy("dst").count().orderBy(F.desc("count"), "dst").limit(3).select(F.col("dst").alias("t"))
    q = starts.crossJoin(ends).where("s <> t").select((F.col("s") * 1_000_000 + F.col("t")).alias("instance_id"), "s", "t", F.lit(4).alias("k"))
    return shown(simple_paths(e, cut(q), 4))


_DOC_E = f"SELECT src, dst FROM ({oracle('doclines')}) g WHERE src NOT IN ({_NOT_BAD}) AND dst NOT IN ({_NOT_BAD})"
add(
    "paths_doclines_quality",
    _doclines,
    f"WITH RECURSIVE e AS ({_DOC_E}), a AS (SELECT src AS s FROM e GROUP BY src ORDER BY count(*) DESC, src LIMIT 3), b AS (SELECT dst AS t FROM e GROUP BY dst ORDER BY count(*) DESC, dst LIMIT 3), "
    f"w(s, t, tail, path, len) AS (SELECT s, t, s, [s], 0 FROM a, b WHERE s <> t UNION ALL SELECT w.s, w.t, e.dst, list_append(w.path, e.dst), w.len + 1 FROM w JOIN e ON e.src = w.tail WHERE w.len < 4 AND w.tail <> w.t AND NOT list_contains(w.path, e.dst)) "
    f"SELECT CAST(len AS BIGINT) AS len, {STR} FROM w WHERE tail = t AND len > 0",
)
add("induced_quality_docs", lambda spark, d: graph(spark, d, "doclines").induced(sql(spark, d, _QUALITY)).edges.select("src", "dst", "w"), f"SELECT src, dst, w FROM ({oracle('doclines')}) g WHERE src IN ({_QUALITY}) AND dst IN ({_QUALITY})")

# --- cycles -----------------------------------------------------------------------------------------

HUB = 11  # on 45 of the cycles of at most 4 edges of trade100 at sf0.01
CYCLES = {"trade100": 4, "trade50": 4, "partchain": 4, "payflow": 3, "custchain": 3, "useritem": 4, "knn": 3, "bigrams": 3, "schema": 4, "navlinks": 3, "doclines": 4}


def _cycles(g: str, k: int, **how) -> Query:
    return lambda spark, d: all_cycles(cut(graph(spark, d, g).edges), k, **how).select(F.col("len").cast("long").alias("len"), path_string().alias("cycle_str"))


HUBS = ("bigrams", "useritem")  # graphs of hubs, or of very many cycles
for g, k in CYCLES.items():
    if g != "schema":
        add(f"cycles_all_{g}", _cycles(g, k, strategy="hubs") if g in HUBS else _cycles(g, k), f"{cycle_walks(oracle(g), k)} SELECT CAST(len AS BIGINT) AS len, array_to_string(path, '>') AS cycle_str FROM w WHERE tail = root AND len > 0")
for g in ("trade100", "payflow", "partchain"):
    k = CYCLES[g]
    add(f"cycles_by_len_{g}", (lambda q: lambda spark, d: q(spark, d).groupBy("len").agg(F.count(F.lit(1)).alias("cycles")))(_cycles(g, k)), f"{cycle_walks(oracle(g), k)} SELECT CAST(len AS BIGINT) AS len, count(*) AS cycles FROM w WHERE tail = root AND len > 0 GROUP BY len")
for strategy in ("task", "split", "relational", "bidirectional", "direct"):
    add("cycles_through_trade" if strategy == "task" else f"cycles_through_{strategy}", _paths("trade100", HUB, HUB, 4, strategy=strategy), found(oracle("trade100"), HUB, HUB, 4))
for scheme in COMPLETE:
    if scheme != "tight":
        add(f"cycles_through_{scheme}", _paths("trade100", HUB, HUB, 4, scheme=scheme), found(oracle("trade100"), HUB, HUB, 4))


def _split_cycles(spark: SparkSession, d: str) -> DataFrame:
    e = cut(graph(spark, d, "trade100").split_node(HUB, 1000 + HUB, 2000 + HUB).edges)
    p = simple_paths(e, asked(spark, [(0, 1000 + HUB, 2000 + HUB, 4)], e), 4)
    return shown(p.withColumn("path", F.transform("path", lambda x: F.when(x > 1000, F.lit(HUB).cast("long")).otherwise(x))))


add("split_cycles_trade", _split_cycles, found(oracle("trade100"), HUB, HUB, 4))
for g in ("navlinks", "trade50", "doclines"):
    add(f"cycles_scc_reduced_{g}", (lambda g, k: lambda spark, d: all_cycles(cut(graph(spark, d, g).edges), k, reduce=True).select(F.col("len").cast("long").alias("len"), path_string().alias("cycle_str")))(g, CYCLES[g]), ORACLES[f"cycles_all_{g}"])
add("viable_roots_payflow", lambda spark, d: L.viable_roots(cut(graph(spark, d, "payflow").edges), 3), f"{cycle_walks(oracle('payflow'), 3)} SELECT DISTINCT root FROM w WHERE tail = root AND len > 0")

# --- labels and reductions ----------------------------------------------------------------------------


def _dist(edges: str, s, k: int, back: bool = False) -> str:
    a, b = ("dst", "src") if back else ("src", "dst")
    return f"WITH RECURSIVE e AS ({edges}), r(node, d) AS (SELECT {lit(s)}, 0 UNION SELECT e.{b}, r.d + 1 FROM r JOIN e ON e.{a} = r.node WHERE r.d < {k})"


def _one(spark: SparkSession, e: DataFrame, s) -> DataFrame:
    return spark.createDataFrame([(0, s)], f"instance_id bigint, node {e.schema['src'].dataType.simpleString()}")


def _bfs(g: str, s, k: int, back: bool = False) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        made = graph(spark, d, g)
        e = cut((made.reverse() if back else made).edges)
        return L.distances(e, _one(spark, e, s), k).select("node", F.col("d").cast("long").alias("d"))

    return run


_MIN = "SELECT node, CAST(min(d) AS BIGINT) AS d FROM r GROUP BY node"
add("bfs_trade", _bfs("trade50", 7, 10), f"{_dist(oracle('trade50'), 7, 10)} {_MIN}")
add("rev_bfs_payflow", _bfs("payflow", 46, 3, True), f"{_dist(oracle('payflow'), 46, 3, True)} {_MIN}")
add("reach_within_navlinks", _bfs("navlinks", "/de", 5), f"{_dist(oracle('navlinks'), '/de', 5)} {_MIN}")
add("eccentricity_partchain", lambda spark, d: _bfs("partchain", 1, 6)(spark, d).agg(F.max("d").alias("eccentricity"), F.count(F.lit(1)).alias("reached")), f"{_dist(oracle('partchain'), 1, 6)} SELECT max(d) AS eccentricity, count(*) AS reached FROM ({_MIN}) m")


def _reldist(spark: SparkSession, d: str) -> DataFrame:
    e = cut(graph(spark, d, "trade100").edges)
    avoid = spark.createDataFrame([(1,), (5,), (9,), (14,)], "id bigint")
    return L.relative_distances(e, avoid, 3, 10).select("node", F.col("d").cast("long").alias("d"))


add("reldist_trade", _reldist, f"WITH RECURSIVE e AS ({oracle('trade100')}), r(node, d) AS (SELECT CAST(3 AS BIGINT), 0 UNION SELECT e.dst, r.d + 1 FROM r JOIN e ON e.src = r.node WHERE r.d < 10 AND r.node NOT IN (1, 5, 9, 14)) {_MIN}")


def _budget(what: str) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        e = cut(graph(spark, d, "partchain").edges)
        sub = L.budget_subgraph(e, asked(spark, [(0, 1, 2, 7)], e), 7)
        return sub.select("src", "dst") if what == "edges" else sub.select(F.col("src").alias("id")).union(sub.select("dst")).distinct()

    return run


_BUDGET = f"WITH RECURSIVE e AS ({oracle('partchain')}), f(node, d) AS (SELECT CAST(1 AS BIGINT), 0 UNION SELECT e.dst, f.d + 1 FROM f JOIN e ON e.src = f.node WHERE f.d < 6), b(node, d) AS (SELECT CAST(2 AS BIGINT), 0 UNION SELECT e.src, b.d + 1 FROM b JOIN e ON e.dst = b.node WHERE b.d < 6), x AS (SELECT e.src, e.dst FROM e JOIN (SELECT node, min(d) AS d FROM f GROUP BY node) fs ON fs.node = e.src JOIN (SELECT node, min(d) AS d FROM b GROUP BY node) bt ON bt.node = e.dst WHERE fs.d + 1 + bt.d <= 7)"
add("budget_edges_partchain", _budget("edges"), f"{_BUDGET} SELECT src, dst FROM x")
add("budget_nodes_partchain", _budget("nodes"), f"{_BUDGET} SELECT src AS id FROM x UNION SELECT dst FROM x")


def _scc(g: str) -> Query:
    return lambda spark, d: L.components(cut(graph(spark, d, g).edges), directed=True).select("id", "component")


def _scc_sql(edges: str) -> str:
    return f"WITH RECURSIVE e AS ({edges}), n AS (SELECT src AS id FROM e UNION SELECT dst FROM e), r(a, b) AS (SELECT id, id FROM n UNION SELECT r.a, e.dst FROM r JOIN e ON e.src = r.b) SELECT x.a AS id, min(x.b) AS component FROM r x JOIN r y ON x.a = y.b AND x.b = y.a GROUP BY x.a"


add("scc_trade50", _scc("trade50"), _scc_sql(oracle("trade50")))
add("scc_navlinks", _scc("navlinks"), _scc_sql(oracle("navlinks")))
add("scc_doclines", _scc("doclines"), _scc_sql(oracle("doclines")))
add("wcc_turns", lambda spark, d: L.components(cut(graph(spark, d, "turns").edges)).select("id", "component"), f"WITH RECURSIVE g AS ({oracle('turns')}), e AS (SELECT src, dst FROM g UNION SELECT dst, src FROM g), r(a, b) AS (SELECT src, src FROM e UNION SELECT r.a, e.dst FROM r JOIN e ON e.src = r.b) SELECT a AS id, min(b) AS component FROM r GROUP BY a")
add("walk_upper_bound_payflow", lambda spark, d: walk_upper_bound(cut(graph(spark, d, "payflow").edges), 8, 46, 4).select(F.col("len").cast("long").alias("len"), "walks"), f"WITH RECURSIVE e AS ({oracle('payflow')}), w(node, len) AS (SELECT CAST(8 AS BIGINT), 0 UNION ALL SELECT e.dst, w.len + 1 FROM w JOIN e ON e.src = w.node WHERE w.len < 4 AND (w.len = 0 OR w.node <> 46)) SELECT CAST(len AS BIGINT) AS len, count(*) AS walks FROM w WHERE node = 46 AND len > 0 GROUP BY len")

# --- golden graphs, worst cases, baselines and measures ----------------------------------------------------

for name, query, text in X.REGISTERED:
    add(name, query, text)
add("circuit_trade50", X.unbounded("trade50", 7, 9, "circuit"), found(oracle("trade50"), 7, 9, 25))
add("backtrack_trade25", X.unbounded("trade25", 19, 9, "backtrack"), found(oracle("trade25"), 19, 9, 25))


CAPPED = {1: 3, 2: 3, 3: 2, 7: 2}  # target: k, from supplier 0
CAP = 5000


def _capped(spark: SparkSession, d: str) -> DataFrame:
    e = cut(graph(spark, d, "supplychain").edges)
    q = cut(asked(spark, [(t, 0, t, k) for t, k in CAPPED.items()], e))
    return capped_counts(simple_paths(e, q, 3, cap=CAP), q, CAP)


add("capped_supplychain", _capped, " UNION ALL ".join(f"SELECT * FROM ({found(oracle('supplychain'), 0, t, k, f'CAST({t} AS BIGINT) AS instance_id, least(count(*), {CAP}) AS outputs, count(*) >= {CAP} AS capped')}) x{t}" for t, k in CAPPED.items()))
_FIRST = found(oracle("trade100"), 3, 9, 4, f"CAST(len AS BIGINT) AS len, {STR}, row_number() OVER (ORDER BY path) AS r")
for strategy in ("task", "relational", "split", "direct", "auto"):
    add(f"cap_{strategy}_trade", _paths("trade100", 3, 9, 4, strategy=strategy, cap=17), f"SELECT len, path_str FROM ({_FIRST}) x WHERE r <= 17")


def _inside(spark: SparkSession, d: str) -> DataFrame:
    return L.reduce_to_scc(cut(graph(spark, d, "trade50").edges)).select("src", "dst")


add("reduce_to_scc_trade50", _inside, f"WITH c AS ({_scc_sql(oracle('trade50'))}) SELECT e.src, e.dst FROM ({oracle('trade50')}) e JOIN c a ON a.id = e.src JOIN c b ON b.id = e.dst WHERE a.component = b.component")


def _chain(spark: SparkSession, d: str) -> DataFrame:
    """Chains of 400 nodes in a shuffled order, far longer than any fixed number of rounds of neighbours."""
    e = spark.range(1200).where("id % 400 <> 399").select((F.col("id") * 7919 % 1200).alias("src"), ((F.col("id") + 1) * 7919 % 1200).alias("dst"))
    return L.components(cut(e)).groupBy("component").agg(F.count(F.lit(1)).alias("nodes"))


add("wcc_long_chains", _chain, "SELECT min(id * 7919 % 1200) AS component, count(*) AS nodes FROM (SELECT unnest(range(1200)) AS id) x GROUP BY id // 400")
add("weighted_paths_trade", X.weighted_trade, f"WITH RECURSIVE e AS ({oracle('trade100')}), w(tail, path, cost) AS (SELECT CAST(3 AS BIGINT), [CAST(3 AS BIGINT)], CAST(0 AS BIGINT) UNION ALL SELECT e.dst, list_append(w.path, e.dst), w.cost + e.w FROM w JOIN e ON e.src = w.tail WHERE w.tail <> 9 AND w.cost + e.w <= {X.WEIGHT_BUDGET} AND NOT list_contains(w.path, e.dst)) SELECT cost, {STR} FROM w WHERE tail = 9")


def _multi_target(spark: SparkSession, d: str) -> DataFrame:
    g = graph(spark, d, "trade100").super_sink(spark.createDataFrame([(9,), (14,)], "id bigint"), 9999)
    e = cut(g.edges)
    p = simple_paths(e, asked(spark, [(0, 3, 9999, 4)], e), 4)
    return shown(p.select((F.col("len") - 1).alias("len"), F.slice("path", 1, F.size("path") - 1).alias("path")))


add("multi_target_trade", _multi_target, f"WITH RECURSIVE e AS ({oracle('trade100')}), w(tail, path, len) AS (SELECT CAST(3 AS BIGINT), [CAST(3 AS BIGINT)], 0 UNION ALL SELECT e.dst, list_append(w.path, e.dst), w.len + 1 FROM w JOIN e ON e.src = w.tail WHERE w.len < 3 AND NOT list_contains(w.path, e.dst)) SELECT CAST(len AS BIGINT) AS len, {STR} FROM w WHERE tail IN (9, 14) AND len > 0")

# --- operators around the methods ------------------------------------------------------------------------------


def same(name: str, text: str, duck_text: str | None = None) -> None:
    """A query whose SQL is common to both engines (or nearly so)."""
    add(name, lambda spark, d: sql(spark, d, text), duck_text or text)


add("scan_edges_trade", lambda spark, d: graph(spark, d, "trade600").edges.select("src", "dst", "w"), oracle("trade600"))
for g in ("partchain", "useritem", "custchain", "navlinks", "bigrams", "turns", "knn", "passages", "schema", "supplychain"):
    add(f"graph_{g}", (lambda g: lambda spark, d: graph(spark, d, g).edges.groupBy("src").agg(F.count(F.lit(1)).alias("out_degree"), F.sum("w").cast("long").alias("w")))(g), f"SELECT src, count(*) AS out_degree, CAST(sum(w) AS BIGINT) AS w FROM ({oracle(g)}) g GROUP BY src")
add("lead_payflow", lambda spark, d: graph(spark, d, "payflow").edges.select("src", "dst", "w"), oracle("payflow"))
for g in ("payflow", "trade100"):
    o = oracle(g)
    add(f"degrees_{g}", (lambda g: lambda spark, d: graph(spark, d, g).degrees())(g), f"SELECT id, count(*) FILTER (o = 1) AS out_degree, count(*) FILTER (o = 0) AS in_degree FROM (SELECT src AS id, 1 AS o FROM ({o}) a UNION ALL SELECT dst, 0 FROM ({o}) b) x GROUP BY id")
add("degree_full_outer", lambda spark, d: _full_outer(spark, d), f"SELECT coalesce(a.id, b.id) AS id, coalesce(a.n, 0) AS trade50, coalesce(b.n, 0) AS trade100 FROM (SELECT src AS id, count(*) AS n FROM ({oracle('trade50')}) x GROUP BY src) a FULL OUTER JOIN (SELECT dst AS id, count(*) AS n FROM ({oracle('trade100')}) y GROUP BY dst) b ON a.id = b.id")


def _full_outer(spark: SparkSession, d: str) -> DataFrame:
    """Out-degrees in one graph beside in-degrees in another, nodes of either."""
    a = graph(spark, d, "trade50").edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("a"))
    b = graph(spark, d, "trade100").edges.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("b"))
    return a.join(b, "id", "full_outer").select("id", F.coalesce("a", F.lit(0)).alias("trade50"), F.coalesce("b", F.lit(0)).alias("trade100"))


add("density_trade", lambda spark, d: graph(spark, d, "trade200").density(), f"WITH e AS ({oracle('trade200')}), n AS (SELECT count(*) AS n FROM (SELECT src FROM e UNION SELECT dst FROM e) x), m AS (SELECT count(*) AS m FROM e) SELECT n, m, round(m / (n * (n - 1)), 6) AS density FROM n, m")
add("adjlist_roundtrip", lambda spark, d: _adjacency(spark, d), f"SELECT src, dst FROM ({oracle('trade100')}) g")


def _adjacency(spark: SparkSession, d: str) -> DataFrame:
    """Edges as adjacency-list lines and back."""
    e = graph(spark, d, "trade100").edges
    lines = e.groupBy("src").agg(F.sort_array(F.collect_list(F.struct("ord", "dst"))).alias("n")).select(F.concat_ws(" ", F.col("src").cast("string"), F.array_join(F.transform("n", lambda x: x["dst"].cast("string")), " ")).alias("value"))
    return datasource.adjacency(lines).select("src", "dst")


add("edges_urgent", lambda spark, d: table(spark, d, "orders").where("o_orderpriority = '1-URGENT'").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("orders")), "SELECT o_custkey, count(*) AS orders FROM orders WHERE o_orderpriority = '1-URGENT' GROUP BY o_custkey")
add("two_hop_partchain", lambda spark, d: _two_hop(spark, d), f"WITH e AS ({oracle('partchain')}) SELECT a.src, count(DISTINCT b.dst) AS two_hop FROM e a JOIN e b ON a.dst = b.src AND a.src <> b.dst GROUP BY a.src")


def _two_hop(spark: SparkSession, d: str) -> DataFrame:
    e = cut(graph(spark, d, "partchain").edges)
    a, b = e.select("src", F.col("dst").alias("mid")), e.select(F.col("src").alias("mid"), F.col("dst").alias("far"))
    return a.join(b, "mid").where("src <> far").groupBy("src").agg(F.countDistinct("far").alias("two_hop"))


add("paths_named_trade", lambda spark, d: _named(spark, d), f"WITH p AS ({found(oracle('trade100'), 3, 9, 3, 'path')}), x AS (SELECT array_to_string(path, '>') AS path_str, unnest(path) AS id, generate_subscripts(path, 1) AS i FROM p) SELECT path_str, string_agg(n_name, '>' ORDER BY i) AS names FROM x JOIN nation ON n_nationkey = id GROUP BY path_str")


def _named(spark: SparkSession, d: str) -> DataFrame:
    """Nation names onto paths; nation has 25 rows by the schema's definition."""
    e = cut(graph(spark, d, "trade100").edges)
    p = simple_paths(e, asked(spark, [(0, 3, 9, 3)], e), 3).select(path_string().alias("path_str"), F.posexplode("path").alias("i", "id"))
    names = F.broadcast(table(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("id"), "n_name"))
    return p.join(names, "id").groupBy("path_str").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("i", "n_name"))), lambda x: x["n_name"]), ">").alias("names"))


_P4 = f"({found(oracle('trade100'), 3, 9, 4, 'len, path')}) p"


def _trade4(spark: SparkSession, d: str) -> DataFrame:
    e = cut(graph(spark, d, "trade100").edges)
    return simple_paths(e, asked(spark, [(0, 3, 9, 4)], e), 4)


add("paths_by_len_trade", lambda spark, d: _trade4(spark, d).groupBy(F.col("len").cast("long").alias("len")).agg(F.count(F.lit(1)).alias("paths")), f"SELECT CAST(len AS BIGINT) AS len, count(*) AS paths FROM {_P4} GROUP BY len")


def _grouped(spark: SparkSession, d: str, how: str, second: str, at: int) -> DataFrame:
    """Paths counted by rollup or cube; the grand total is a plain count, which is there without any path."""
    p = cut(_trade4(spark, d).select(F.col("len").cast("long").alias("len"), F.element_at("path", at).alias(second)))
    parts = getattr(p, how)("len", second).agg(F.count(F.lit(1)).alias("paths"), F.grouping_id().alias("g")).where("g < 3").drop("g")
    return parts.unionByName(p.agg(F.count(F.lit(1)).alias("paths")), allowMissingColumns=True)


add("rollup_len_trade", lambda spark, d: _grouped(spark, d, "rollup", "second", 2), f"SELECT CAST(len AS BIGINT) AS len, path[2] AS second, count(*) AS paths FROM {_P4} GROUP BY ROLLUP (CAST(len AS BIGINT), path[2])")
add("cube_len_src", lambda spark, d: _grouped(spark, d, "cube", "last_but_one", -2), f"SELECT CAST(len AS BIGINT) AS len, path[-2] AS last_but_one, count(*) AS paths FROM {_P4} GROUP BY CUBE (CAST(len AS BIGINT), path[-2])")
add("pivot_len_second", lambda spark, d: _trade4(spark, d).groupBy(F.element_at("path", 2).alias("second")).pivot("len", [2, 3, 4]).count().select("second", *[F.coalesce(F.col(str(i)), F.lit(0)).alias(f"len{i}") for i in (2, 3, 4)]).where("len2 + len3 + len4 > 0"), f"SELECT path[2] AS second, {', '.join(f'count(*) FILTER (len = {i}) AS len{i}' for i in (2, 3, 4))} FROM {_P4} WHERE len > 1 GROUP BY path[2]")
add("node_participation", lambda spark, d: _trade4(spark, d).select(F.explode("path").alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("paths")), f"SELECT id, count(*) AS paths FROM (SELECT unnest(path) AS id FROM {_P4}) x GROUP BY id")
_EDGES_OF = "SELECT path[i] AS src, path[i + 1] AS dst FROM (SELECT path, unnest(generate_series(1, len)) AS i FROM {p}) x".replace("{p}", _P4)
add("edge_participation", lambda spark, d: _path_edges(spark, d).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("paths")), f"SELECT src, dst, count(*) AS paths FROM ({_EDGES_OF}) y GROUP BY src, dst")
add("path_edges_exploded", lambda spark, d: _path_edges(spark, d), _EDGES_OF)


def _path_edges(spark: SparkSession, d: str) -> DataFrame:
    hops = F.transform(F.sequence(F.lit(1), F.col("len")), lambda i: F.struct(F.element_at("path", i).alias("src"), F.element_at("path", i + 1).alias("dst")))
    return _trade4(spark, d).select(F.inline(hops))


add("disjoint_halves", lambda spark, d: _disjoint(spark, d), f"WITH p AS (SELECT array_to_string(path, '>') AS s, path[2:-2] AS inner_nodes FROM {_P4} WHERE len = 3) SELECT a.s AS a, b.s AS b FROM p a JOIN p b ON a.s < b.s AND NOT list_has_any(a.inner_nodes, b.inner_nodes)")


def _disjoint(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of internally disjoint 3-hop paths of one query."""
    p = cut(_trade4(spark, d).where("len = 3").select(path_string().alias("s"), F.slice("path", 2, 2).alias("inner")))
    return p.alias("a").join(p.alias("b"), (F.col("a.s") < F.col("b.s")) & ~F.arrays_overlap("a.inner", "b.inner")).select(F.col("a.s").alias("a"), F.col("b.s").alias("b"))


add("cycle_canonical", lambda spark, d: _canonical(spark, d), f"{cycle_walks(oracle('trade100'), 3)} SELECT array_to_string(path, '>') AS cycle_str FROM w WHERE tail = root AND len = 3")


def _canonical(spark: SparkSession, d: str) -> DataFrame:
    """3-cycles by joins, brought to canonical rotation with array functions."""
    e = cut(graph(spark, d, "trade100").edges.select("src", "dst"))
    a, b, c = (e.toDF(x, y) for x, y in (("x", "y"), ("y", "z"), ("z", "x2")))
    tri = a.join(b, "y").join(c, "z").where("x = x2 and x <> z").select(F.array("x", "y", "z").alias("c"))
    at = F.array_position("c", F.array_min("c")).cast("int")
    turned = tri.withColumn("at", at).select(F.concat(F.expr("slice(c, at, 3)"), F.expr("slice(c, 1, at - 1)"), F.array(F.array_min("c"))).alias("path"))
    return turned.distinct().select(path_string().alias("cycle_str"))


add("scan_order_rank", lambda spark, d: graph(spark, d, "trade100").edges.select("src", "dst", F.col("ord").cast("long").alias("ord")), f"SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dst) AS ord FROM ({oracle('trade100')}) g")
add("topk_edges_trade", lambda spark, d: graph(spark, d, "trade600").edges.orderBy(F.desc("w"), "src", "dst").limit(10).select("src", "dst", "w"), f"SELECT src, dst, w FROM ({oracle('trade600')}) g ORDER BY w DESC, src, dst LIMIT 10")
add("sinks_anti", lambda spark, d: _sinks(spark, d), f"WITH e AS ({oracle('navlinks')}) SELECT DISTINCT dst AS id FROM e WHERE dst NOT IN (SELECT src FROM e)")


def _sinks(spark: SparkSession, d: str) -> DataFrame:
    e = cut(graph(spark, d, "navlinks").edges)
    return e.select(F.col("dst").alias("id")).distinct().join(e.select(F.col("src").alias("id")), "id", "left_anti")


_K = oracle("payflow")
add("reciprocal_intersect", lambda spark, d: _setop(spark, d, "intersect"), f"SELECT src, dst FROM ({_K}) a INTERSECT SELECT dst, src FROM ({_K}) b")
add("oneway_except", lambda spark, d: _setop(spark, d, "subtract"), f"SELECT src, dst FROM ({_K}) a EXCEPT SELECT dst, src FROM ({_K}) b")
add("sym_union_payflow", lambda spark, d: _setop(spark, d, "union").distinct(), f"SELECT src, dst FROM ({_K}) a UNION SELECT dst, src FROM ({_K}) b")


def _setop(spark: SparkSession, d: str, op: str) -> DataFrame:
    e = cut(graph(spark, d, "payflow").edges.select("src", "dst"))
    return getattr(e, op)(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


_TEMPORAL = "SELECT a.user_id AS a, b.user_id AS b, c.user_id AS c FROM p a JOIN p b ON b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR AND a.user_id <> b.user_id JOIN p c ON c.ts > b.ts AND c.ts <= b.ts + INTERVAL 2 HOUR AND c.user_id <> b.user_id AND c.user_id <> a.user_id"
add("temporal_paths_payflow", lambda spark, d: _temporal(spark, d), f"WITH p AS (SELECT ts, user_id FROM events WHERE event_type = 'purchase') SELECT a, count(*) AS paths FROM ({_TEMPORAL}) t GROUP BY a")


def _temporal(spark: SparkSession, d: str) -> DataFrame:
    """Time-respecting two-hop purchase chains within two hours a hop, counted by prefix sums in overlapping stretches of time; see operators.chains."""
    p = table(spark, d, "events").where("event_type = 'purchase'").select(micros("ts").alias("at"), "user_id")
    return chains.two_hop_chains(p, 7_200_000_000)


add("asof_events", lambda spark, d: _asof(spark, d), "SELECT p.event_id, c.event_id AS last_click FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'click' GROUP BY user_id, ts) c ON p.user_id = c.user_id AND p.ts >= c.ts")


def _asof(spark: SparkSession, d: str) -> DataFrame:
    """Each purchase with its user's last click, by one ordered pass over the union."""
    e = table(spark, d, "events").where("event_type in ('purchase', 'click')").select("event_id", "ts", "user_id", (F.col("event_type") == "purchase").cast("int").alias("buy"))
    w = Window.partitionBy("user_id").orderBy("ts", "buy", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("last_click", F.last(F.when(F.col("buy") == 0, F.col("event_id")), True).over(w)).where("buy = 1").select("event_id", "last_click")


add("pair_queries_trade", lambda spark, d: _pairs(spark, d)[1].select("instance_id", "s", "t"), f"WITH n AS (SELECT src AS id FROM ({oracle('trade100')}) a UNION SELECT dst FROM ({oracle('trade100')}) b) SELECT a.id * 1000 + b.id AS instance_id, a.id AS s, b.id AS t FROM n a CROSS JOIN n b WHERE a.id <> b.id")
same("payflow_by_day", "SELECT CAST(CAST(date_trunc('day', ts) AS DATE) AS STRING) AS day, count(*) AS purchases, count(DISTINCT user_id) AS users FROM {events} WHERE event_type = 'purchase' GROUP BY CAST(date_trunc('day', ts) AS DATE)")
same("gaps_days", "SELECT user_id, max(g) AS longest_gap FROM (SELECT user_id, datediff(CAST(lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS DATE), CAST(ts AS DATE)) AS g FROM {events}) x GROUP BY user_id", "SELECT user_id, CAST(max(g) AS INTEGER) AS longest_gap FROM (SELECT user_id, date_diff('day', CAST(ts AS DATE), CAST(lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS DATE)) AS g FROM {events}) x GROUP BY user_id")
same("json_item", "SELECT event_type, CAST(get_json_object(props, '$.k') AS BIGINT) AS item, count(*) AS n FROM {events} GROUP BY event_type, CAST(get_json_object(props, '$.k') AS BIGINT)", "SELECT event_type, CAST(json_extract_string(props, '$.k') AS BIGINT) AS item, count(*) AS n FROM {events} GROUP BY ALL")
same("lcg_nodes", "SELECT id, (id * 1103515245 + 12345) % 2147483648 AS x FROM (SELECT CAST(n_nationkey AS BIGINT) AS id FROM {nation}) t")
same("running_steps", "SELECT user_id, event_id, sum(1) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS n, ntile(4) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS quarter, dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS kind FROM {events}", "SELECT user_id, event_id, CAST(sum(1) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS n, CAST(ntile(4) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS INTEGER) AS quarter, CAST(dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS INTEGER) AS kind FROM {events}")
add("paths_sink_roundtrip", lambda spark, d: datasource.sink_roundtrip(_trade4(spark, d)).select(F.col("len").cast("long").alias("len"), "path_str"), found(oracle("trade100"), 3, 9, 4))
add("bucketed_two_hop", lambda spark, d: datasource.bucketed_two_hop(cut(graph(spark, d, "partchain").edges.select("src", "dst"))), f"WITH e AS ({oracle('partchain')}) SELECT a.src, b.dst, count(*) AS walks FROM e a JOIN e b ON a.dst = b.src GROUP BY a.src, b.dst")
add("udf_is_simple", lambda spark, d: _simple(spark, d), f"SELECT true AS simple, count(*) AS paths FROM {_P4}")


def _simple(spark: SparkSession, d: str) -> DataFrame:
    """Paths by whether they are simple; the count of simple ones is there, as 0, without any path."""
    flags = _trade4(spark, d).select(sqlapi.is_simple("path").alias("simple"), F.lit(1).alias("n"))
    none = spark.range(1).select(F.lit(True).alias("simple"), F.lit(0).alias("n"))
    return flags.unionByName(none).groupBy("simple").agg(F.sum("n").alias("paths"))


add("udtf_paths_trade", sqlapi.udtf_query, found(oracle("trade100"), 3, 9, 3))
add("udtf_lateral_paths", sqlapi.lateral_query, f"SELECT CAST(q AS BIGINT) AS q, count(*) AS paths FROM (SELECT 3 AS q, len FROM ({found(oracle('trade100'), 3, 9, 3)}) a UNION ALL SELECT 4, len FROM ({found(oracle('trade100'), 3, 9, 4)}) b) x GROUP BY q")
add("generated_source_rows", datasource.generated_query, "SELECT 'clique_trap' AS family, CAST(56 AS BIGINT) AS edges UNION ALL SELECT 'hub_breaker', 30 UNION ALL SELECT 'small_world', 6000")

_UND = f"SELECT src, dst FROM ({oracle('payflow')}) a UNION SELECT dst, src FROM ({oracle('payflow')}) b"


def _undirected(spark: SparkSession, d: str) -> DataFrame:
    e = cut(Graph(graph(spark, d, "payflow").edges).symmetrize().edges)
    return shown(simple_paths(e, asked(spark, [(0, 8, 46, 3)], e), 3))


add("undirected_paths_payflow", _undirected, found(_UND, 8, 46, 3))
same("event_ranks", "SELECT event_id, CAST(rank() OVER w AS BIGINT) AS r, CAST(round(percent_rank() OVER w * 1000) AS BIGINT) AS pr, lag(event_id) OVER w AS before, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND CURRENT ROW) AS near FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
same("grouping_sets_events", "SELECT event_type, CAST(user_id % 5 AS BIGINT) AS part, count(*) AS n, count(DISTINCT user_id) AS users, CAST(grouping(event_type) AS BIGINT) AS g FROM {events} GROUP BY GROUPING SETS ((event_type), (user_id % 5), (event_type, user_id % 5), ())")
same("dead_ends_left_outer", f"WITH e AS ({GRAPHS['supplychain']}) SELECT s_suppkey, count(e.dst) AS successors FROM {{supplier}} LEFT JOIN e ON e.src = s_suppkey GROUP BY s_suppkey")
add("approx_users", lambda spark, d: table(spark, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5).alias("median")))

# --- streams ----------------------------------------------------------------------------------------------------

for name, query, text in stream.REGISTERED:
    add(name, query, text)
