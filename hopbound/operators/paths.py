"""Simple paths and cycles of bounded length: physical strategies over one search kernel.

`task`: every query searches its own reduced subgraph in one task. `split`: prefixes of a query are expanded by joins and
each is searched in a task. `relational`: all hops are joins pruned by exact target distances. `bidirectional`: halves
meet in the middle. `direct`: small graphs go to one task per query as they are. `auto`: see plans.choose. All return instance_id, len, path; the first also seq, the place in lexicographic scan order.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hopbound.functions.search import COMPLETE, Csr, distances_to, search, stream

from .cut import cut, is_empty
from .labels import budget_subgraph, cycle_subgraphs, reduce_to_scc, to_target

STRATEGIES = ("task", "split", "relational", "bidirectional", "direct")
DIRECT_ROWS = 500_000  # edges times queries up to which auto searches without reduction
SHIPPED_CYCLE_EDGES = 500_000


def _kinds(edges: DataFrame, queries: DataFrame) -> tuple[str, str]:
    return queries.schema["instance_id"].dataType.simpleString(), edges.schema["src"].dataType.simpleString()


def simple_paths(edges: DataFrame, queries: DataFrame, max_k: int, scheme: str = "tight", strategy: str = "task", cap: int | None = None, depth: int = 1) -> DataFrame:
    """Paths of every query (instance_id, s, t, k) over edges (src, dst, ord); s = t gives the cycles through s.

    max_k bounds every k. Queries whose nodes are absent or not connected give no rows. cap leaves the first so many outputs of
    each query, in scan order, whatever the strategy; `bidirectional` knows no scan order and refuses it. Strategies of joins list all paths, so they
    refuse schemes that do not (`split` takes them: its kernels lose what the scheme loses). depth is the prefix length of split. `auto` lets plans.choose pick.
    """
    if strategy in ("relational", "bidirectional") and scheme not in COMPLETE:
        raise ValueError(f"{strategy} lists all paths; {scheme} may not")
    if strategy == "bidirectional" and cap is not None:
        raise ValueError("bidirectional has no scan order to cap by")
    if strategy == "auto":
        from hopbound.plans.choose import run_planned

        return run_planned(edges, queries, max_k, scheme, cap)
    if strategy == "direct":
        return search_groups(edges.crossJoin(F.broadcast(queries)), *_kinds(edges, queries), scheme, cap)
    if strategy == "task":
        return search_groups(budget_subgraph(edges, queries, max_k).join(queries, "instance_id"), *_kinds(edges, queries), scheme, cap)
    if strategy == "relational":
        return first_of_each(expand(edges, queries, max_k)[0], ["ords"], cap)
    if strategy == "split":
        return split_paths(edges, queries, max_k, scheme, depth, cap)
    if strategy == "bidirectional":
        return meet_in_middle(edges, queries, max_k)
    raise ValueError(strategy)


def first_of_each(paths: DataFrame, order: list[str], cap: int | None) -> DataFrame:
    """The first cap paths of every instance by the order columns; all if cap is None."""
    if cap is None:
        return paths
    w = Window.partitionBy("instance_id").orderBy(*order)
    return paths.withColumn("_n", F.row_number().over(w)).where(F.col("_n") <= cap).drop("_n")


def capped_counts(paths: DataFrame, queries: DataFrame, cap: int) -> DataFrame:
    """(instance_id, outputs, capped) of every query from its paths under cap: capped if the cap may have cut some off."""
    n = paths.groupBy("instance_id").agg(F.count(F.lit(1)).alias("outputs"))
    return queries.select("instance_id").join(n, "instance_id", "left").select("instance_id", F.coalesce("outputs", F.lit(0)).alias("outputs"), (F.coalesce("outputs", F.lit(0)) >= cap).alias("capped"))


STREAMED = 4096  # paths of a batch that a search hands on before it goes on


def search_groups(rows: DataFrame, id_type: str, node_type: str, scheme: str = "tight", cap: int | None = None) -> DataFrame:
    """Kernel per instance: rows are its edges with s, t, k beside each. Paths leave the task in batches as they are found; none are kept."""
    schema = f"instance_id {id_type}, seq long, len int, path array<{node_type}>, steps_at long"
    names = ["instance_id", "seq", "len", "path", "steps_at"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        edges, first = [], None
        for b in batches:
            if b.num_rows and first is None:
                first = {c: b.column(c)[0].as_py() for c in ("instance_id", "s", "t", "k")}
                kinds = [b.schema.field("instance_id").type, pa.int64(), pa.int32(), pa.list_(b.schema.field("src").type), pa.int64()]
            edges += zip(b.column("src").to_pylist(), b.column("dst").to_pylist(), b.column("ord").to_pylist())
        csr = Csr.of(edges)
        s, t = csr.index(first["s"]), csr.index(first["t"])
        if s is None or t is None:
            return
        out: list[tuple] = []

        def batch() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(zip(*out), kinds)], names)

        for seq, (path, at) in enumerate(stream(csr, s, t, int(first["k"]), scheme, cap), 1):
            out.append((first["instance_id"], seq, len(path) - 1, [csr.names[i] for i in path], at))
            if len(out) == STREAMED:
                yield batch()
                out = []
        if out:
            yield batch()

    return rows.select("instance_id", "src", "dst", "ord", "s", "t", "k").groupBy("instance_id").applyInArrow(run, schema)


def expand(edges: DataFrame, queries: DataFrame, max_k: int, rounds: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(finished paths, open prefixes) after `rounds` hops (max_k unless given), pruned by distances to t before a hop is appended."""
    _, node = _kinds(edges, queries)
    d_t = cut(to_target(edges, queries, max_k - 1)).select("instance_id", F.col("node").alias("dst"), F.col("d").alias("d_t"))
    step = edges.select(F.col("src").alias("tail"), "dst", "ord")
    front = queries.select("instance_id", "t", "k", F.array("s").alias("path"), F.array().cast("array<int>").alias("ords"), F.col("s").alias("tail"))
    done = None
    for h in range(rounds or max_k):
        # only hops that can still arrive meet the prefixes: a hub's other edges would make as many rows again for every prefix that ends there
        toward = step.join(d_t.where(F.col("d_t") < max_k - h), "dst")
        nxt = front.join(toward, ["instance_id", "tail"]).where((F.lit(h) + F.col("d_t") < F.col("k")) & ((F.col("dst") == F.col("t")) | ~F.array_contains("path", F.col("dst"))))
        nxt = cut(nxt.select("instance_id", "t", "k", F.array_append("path", F.col("dst")).alias("path"), F.array_append("ords", F.col("ord").cast("int")).alias("ords"), F.col("dst").alias("tail")))
        hit = nxt.where("tail = t").select("instance_id", F.lit(h + 1).alias("len"), "path", "ords")
        done = hit if done is None else done.unionByName(hit)
        front = nxt.where("tail <> t")
        if is_empty(front):
            break
    return done, front


def split_paths(edges: DataFrame, queries: DataFrame, max_k: int, scheme: str, depth: int, cap: int | None = None) -> DataFrame:
    """Prefixes of `depth` hops, each searched from its end in the graph without its other nodes; outputs are disjoint by prefix."""
    done, front = expand(edges, queries, max_k, depth)
    id_type, node_type = _kinds(edges, queries)
    prefixes = cut(front.select(F.concat_ws("|", F.col("instance_id").cast("string"), F.col("path").cast("string")).alias("prefix"), "instance_id", "path", "ords", F.col("tail").alias("s"), "t", (F.col("k") - depth).alias("k")))
    sub = budget_subgraph(edges, queries, max_k).select("instance_id", "src", "dst", "ord")
    rows = prefixes.join(sub, "instance_id").where((~F.array_contains("path", F.col("dst")) | (F.col("dst") == F.col("t"))) & (~F.array_contains("path", F.col("src")) | (F.col("src") == F.col("s"))))
    found = search_groups(rows.select(F.col("prefix").alias("instance_id"), "src", "dst", "ord", "s", "t", "k"), "string", node_type, scheme, cap)
    whole = found.withColumnRenamed("instance_id", "prefix").withColumnRenamed("path", "rest").join(prefixes.select("prefix", "instance_id", "path", "ords"), "prefix")
    whole = whole.select("instance_id", (F.col("len") + depth).alias("len"), F.concat("path", F.slice("rest", 2, 1_000_000)).alias("path"), "ords", "seq")
    # prefixes in scan order, and within one the order of its search
    return first_of_each(done.select("instance_id", "len", "path", "ords", F.lit(0).cast("long").alias("seq")).unionByName(whole), ["ords", "seq"], cap).select("instance_id", "len", "path")


def meet_in_middle(edges: DataFrame, queries: DataFrame, max_k: int) -> DataFrame:
    """Forward halves of ceil(l/2) hops joined with backward halves of floor(l/2) hops at their common node, and at s where s = t."""
    half = (max_k + 1) // 2
    sub = cut(budget_subgraph(edges, queries, max_k))

    def halves(rows: DataFrame, start: str, avoid: str, rounds: int) -> list[DataFrame]:
        front = queries.select("instance_id", "k", F.col(avoid).alias("avoid"), F.array(start).alias("path"), F.col(start).alias("tail"))
        out = [front]
        for _ in range(rounds):
            nxt = front.where("tail <> avoid OR size(path) = 1").join(rows, ["instance_id"]).where("tail = a").where(~F.array_contains("path", F.col("b")))
            front = cut(nxt.select("instance_id", "k", "avoid", F.array_append("path", F.col("b")).alias("path"), F.col("b").alias("tail")))
            out.append(front)
        return out

    ahead = halves(sub.select("instance_id", F.col("src").alias("a"), F.col("dst").alias("b")), "s", "t", half)
    behind = halves(sub.select("instance_id", F.col("dst").alias("a"), F.col("src").alias("b")), "t", "s", max_k // 2)
    found = None
    for length in range(1, max_k + 1):
        f = ahead[(length + 1) // 2].select("instance_id", "k", F.col("path").alias("p"), "tail", "avoid")
        b = behind[length // 2].select("instance_id", F.col("path").alias("q"), "tail", F.col("avoid").alias("s"))
        f = f.where("tail <> avoid") if length > 1 else f.where("tail = avoid")
        b = b.where("tail <> s")
        met = f.join(b, ["instance_id", "tail"]).where((F.size(F.array_intersect("p", "q")) == F.when(F.col("avoid") == F.col("s"), 2).otherwise(1)) & (F.col("k") >= length))
        met = met.select("instance_id", F.lit(length).alias("len"), F.concat("p", F.slice(F.reverse("q"), 2, 1_000_000)).alias("path"))
        found = met if found is None else found.unionByName(met)
    return found


def all_cycles(edges: DataFrame, k: int, scheme: str = "tight", strategy: str = "joins", reduce: bool = False) -> DataFrame:
    """(root, len, path) of every simple cycle of at most k edges, once, from its least node and closed.

    `joins` finds viable roots and their subgraphs by joins over all roots. `shipped` sends the whole graph (of a checked size) to
    the tasks, which cut out each root's surroundings themselves; `auto` does so up to SHIPPED_CYCLE_EDGES. `hubs` joins halves of cycles without a
    kernel, see cycles_from_hubs, and refuses schemes that may lose cycles. reduce first leaves only edges inside strongly
    connected components, which pays where much of the graph is on no cycle.
    """
    if strategy == "hubs" and scheme not in COMPLETE:
        raise ValueError(f"{strategy} lists all cycles; {scheme} may not")
    edges = reduce_to_scc(edges) if reduce else edges
    if strategy == "hubs":
        return cycles_from_hubs(edges, k)
    node = edges.schema["src"].dataType.simpleString()
    if strategy == "shipped" or strategy == "auto" and edges.limit(SHIPPED_CYCLE_EDGES + 1).count() <= SHIPPED_CYCLE_EDGES:
        return _cycles_shipped(edges, k, scheme, node)
    rows = cycle_subgraphs(edges, k).select("instance_id", "src", "dst", "ord", F.col("instance_id").alias("s"), F.col("instance_id").alias("t"), F.lit(k).alias("k"))
    return search_groups(rows, node, node, scheme).select(F.col("instance_id").alias("root"), "len", "path")


def cycles_from_hubs(edges: DataFrame, k: int) -> DataFrame:
    """(root, len, path) as all_cycles: halves of ceil(l/2) hops ahead and floor(l/2) hops back, joined at their last node.

    Every cycle is put together from its node of most edges, all its other nodes being of fewer (ties: by name), and turned to its least node in the
    end. So halves never pass through a larger hub than they begin at, and those of two hops are at most the sum over all edges of the lesser degree
    of their ends, however large the largest hub is.
    """
    ends = edges.select(F.col("src").alias("id")).unionAll(edges.select(F.col("dst").alias("id")))
    degree = cut(ends.groupBy("id").agg(F.count(F.lit(1)).alias("deg")))
    a, b = degree.select(F.col("id").alias("src"), F.col("deg").alias("src_deg")), degree.select(F.col("id").alias("dst"), F.col("deg").alias("dst_deg"))
    known = cut(edges.select("src", "dst").join(a, "src").join(b, "dst").select("src", "dst", "src_deg", "dst_deg"))

    def halves(x: str, y: str, rounds: int) -> list[DataFrame]:
        step = known.select(F.col(x).alias("x"), F.col(y).alias("y"), F.col(f"{y}_deg").alias("y_deg"))
        front = known.select(F.col(x).alias("hub"), F.col(f"{x}_deg").alias("hub_deg"), F.col(y).alias("tail"), F.col(f"{y}_deg").alias("_d")).where(_below("_d", "tail")).select("hub", "hub_deg", "tail", F.array("tail").alias("inner"))
        out = [front]
        for left in range(rounds - 2, -1, -1):
            nxt = front.join(step, front["tail"] == step["x"]).where(_below("y_deg", "y") & ~F.array_contains("inner", F.col("y")))
            nxt = nxt.select("hub", "hub_deg", F.col("y").alias("tail"), F.array_append("inner", F.col("y")).alias("inner"))
            front = cut(nxt) if left else nxt  # the longest halves are the most rows, and no others grow from them
            out.append(front)
        return out

    ahead, behind = halves("src", "dst", (k + 1) // 2), halves("dst", "src", max(k // 2, 1))
    found = None
    for length in range(2, k + 1):
        p = ahead[(length + 1) // 2 - 1].select("hub", "tail", F.col("inner").alias("p"))
        q = behind[length // 2 - 1].select("hub", "tail", F.slice(F.reverse("inner"), 2, 1_000_000).alias("q"))
        if length > 3:
            one = _joined_in_order(p, q).select("root", F.lit(length).alias("len"), "path")
        else:
            nodes = p.join(q, ["hub", "tail"]).select(F.concat(F.array("hub"), "p", "q").alias("nodes"))
            at = F.array_position("nodes", F.array_min("nodes")).cast("int")
            turned = F.concat(F.slice("nodes", at, F.lit(k)), F.slice("nodes", F.lit(1), at - 1), F.slice("nodes", at, F.lit(1)))
            one = nodes.select(F.array_min("nodes").alias("root"), F.lit(length).alias("len"), turned.alias("path"))
        found = one if found is None else found.unionByName(one)
    return found


HALVES_OF_A_BLOCK = 4096


def _joined_in_order(p: DataFrame, q: DataFrame) -> DataFrame:
    """(root, path) of the cycles hub, p, q from all pairs of halves of one hub and tail without a common node, by the half with the lesser node, then the other.

    Cycles are by far the most rows, and are written in this order: a row differs from the one before it in a few characters, and only those are left
    of it in a compressed table. Halves meet as blocks of sorted lists, so that no cycle is sorted. Either half may have the lesser node, so each pair
    of blocks is gone through from both sides. What is the same for all cycles of a half is made once: what they begin and end with, from
    their least node, if this half has it or the hub is it, and what stands between if the other has it.
    """

    def blocks(halves: DataFrame, inner: str, ahead: bool) -> DataFrame:
        hub, nodes = F.array("hub"), F.col("nodes")
        least = F.array_min(nodes)
        at, first = F.array_position(nodes, least).cast("int"), F.col("hub") < least
        head = F.when(first, F.concat(hub, nodes) if ahead else hub).otherwise(F.slice(nodes, at, F.size(nodes)))
        end = F.when(first, hub if ahead else F.concat(nodes, hub)).otherwise(F.slice(nodes, F.lit(1), at))
        half = F.struct(least.alias("least"), nodes.alias("nodes"), first.alias("first"), head.alias("head"), end.alias("end"), (F.concat(hub, nodes) if ahead else F.concat(nodes, hub)).alias("between"))
        rows = halves.select("hub", "tail", F.col(inner).alias("nodes"))
        block = F.floor((F.row_number().over(Window.partitionBy("hub", "tail").orderBy("nodes")) - 1) / HALVES_OF_A_BLOCK)
        return rows.withColumn("block", block).groupBy("hub", "tail", "block").agg(F.sort_array(F.collect_list(half)).alias(inner)).drop("block")

    both = blocks(p, "p", True).join(blocks(q, "q", False), ["hub", "tail"])
    sides = both.select(F.inline(F.array(F.struct(F.col("p").alias("a"), F.col("q").alias("b")), F.struct(F.col("q").alias("a"), F.col("p").alias("b")))))
    met = sides.select(F.explode("a").alias("a"), "b").select("a", F.explode("b").alias("b"))
    met = met.where((F.col("a.least") < F.col("b.least")) & ~F.arrays_overlap("a.nodes", "b.nodes"))
    return met.select(F.col("a.head")[0].alias("root"), F.concat("a.head", F.when(F.col("a.first"), F.col("b.nodes")).otherwise(F.col("b.between")), "a.end").alias("path"))


def _below(deg: str, node: str) -> Column:
    """Whether a node with its degree comes after the hub of its row."""
    return (F.col(deg) < F.col("hub_deg")) | ((F.col(deg) == F.col("hub_deg")) & (F.col(node) > F.col("hub")))


def _cycles_shipped(edges: DataFrame, k: int, scheme: str, node: str) -> DataFrame:
    sent = edges.sparkSession.sparkContext.broadcast(shipped(edges))
    roots = edges.select("src").distinct().repartition(4 * edges.sparkSession.sparkContext.defaultParallelism)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        whole = None
        for b in batches:
            whole = whole or Csr.of(sent.value)
            out = []
            for root in b["src"].tolist():
                r = whole.index(root)
                near = whole.around(r, k)
                if near is not None:
                    out += [(root, len(p) - 1, [near.names[i] for i in p]) for p in search(near, near.index(root), near.index(root), k, scheme).outputs]
            yield pd.DataFrame({"root": pd.Series([x[0] for x in out], dtype=b["src"].dtype), "len": pd.Series([x[1] for x in out], dtype="int32"), "path": pd.Series([x[2] for x in out], dtype=object)})

    return roots.mapInPandas(run, f"root {node}, len int, path array<{node}>")


def recursive_sql(edges_view: str, s: str, t: str, k: int) -> str:
    """Spark SQL that lists the paths of one query by recursion over a view of edges."""
    return (
        f"WITH RECURSIVE walk(tail, len, path) AS (SELECT {s}, 0, array({s}) UNION ALL "
        f"SELECT e.dst, w.len + 1, array_append(w.path, e.dst) FROM walk w JOIN {edges_view} e ON e.src = w.tail "
        f"WHERE w.len < {k} AND (w.len = 0 OR w.tail <> {t}) AND (e.dst = {t} OR NOT array_contains(w.path, e.dst))) "
        f"SELECT len, path FROM walk WHERE tail = {t} AND len > 0"
    )


def walk_upper_bound(edges: DataFrame, s, t, k: int) -> DataFrame:
    """(len, walks): the numbers of s-t walks by length, an upper bound of the simple paths; one aggregation a hop."""
    spark = edges.sparkSession
    front = spark.createDataFrame([(s,)], f"node {edges.schema['src'].dataType.simpleString()}").withColumn("walks", F.lit(1).cast("decimal(38,0)"))
    out = None
    for h in range(1, k + 1):
        front = cut(front.where((F.col("node") != F.lit(t)) | (F.lit(h) == 1)).join(edges, F.col("node") == F.col("src")).groupBy(F.col("dst").alias("node")).agg(F.sum("walks").cast("decimal(38,0)").alias("walks")))
        hit = front.where(F.col("node") == F.lit(t)).select(F.lit(h).alias("len"), F.col("walks").cast("long").alias("walks"))
        out = hit if out is None else out.unionByName(hit)
    return out


def path_string(c: str = "path"):
    return F.array_join(F.col(c).cast("array<string>"), ">")


MAX_SHIPPED_EDGES = 2_000_000


def shipped(edges: DataFrame) -> list[tuple]:
    """The edges as (src, dst, ord) rows for tasks to search whole; refused beyond MAX_SHIPPED_EDGES."""
    rows = [tuple(r) for r in edges.select("src", "dst", "ord").limit(MAX_SHIPPED_EDGES + 1).collect()]
    if len(rows) > MAX_SHIPPED_EDGES:
        raise ValueError("too many edges to ship; reduce the graph or use strategy='task'")
    return rows


def seeds(csr: Csr, t: int, k: int) -> list[int]:
    return distances_to(csr, t, k)[0]
