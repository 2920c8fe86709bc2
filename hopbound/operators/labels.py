"""Distance labels, reductions and components as joins over the edge table."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .cut import cut, is_empty


MAX_ROUNDS = 100_000  # beyond which loops that go on until nothing changes raise an error


def distances(edges: DataFrame, sources: DataFrame, max_depth: int, within: Column | None = None, bound: DataFrame | None = None) -> DataFrame:
    """(instance_id, node, d): least number of edges from a source, up to max_depth, all instances in the same rounds.

    sources has instance_id, node and perhaps more, which `within` may use with src and dst to limit the edges taken.
    bound (instance_id, node, rest) keeps only nodes with d + rest <= its column k.
    """
    more = [c for c in sources.columns if c not in ("instance_id", "node")]
    layer = cut(sources.select("instance_id", "node", *more, F.lit(0).alias("d")).dropDuplicates(["instance_id", "node"]))
    seen = layer
    step = edges.select("src", "dst")
    for depth in range(1, max_depth + 1):
        nxt = layer.join(step, layer["node"] == step["src"])
        nxt = nxt if within is None else nxt.where(within)
        nxt = nxt.select("instance_id", F.col("dst").alias("node"), *more, F.lit(depth).alias("d")).dropDuplicates(["instance_id", "node"])
        nxt = nxt.join(seen.select("instance_id", "node"), ["instance_id", "node"], "left_anti")
        if bound is not None:
            nxt = nxt.join(bound, ["instance_id", "node"]).where(F.col("d") + F.col("rest") <= F.col("k")).select("instance_id", "node", *more, "d")
        layer = cut(nxt)
        if is_empty(layer):
            break
        seen = seen.unionByName(layer)
    return seen.select("instance_id", "node", "d")


def relative_distances(edges: DataFrame, avoid: DataFrame, source, max_depth: int) -> DataFrame:
    """(node, d): distances from source over paths whose inner nodes are outside avoid (id); an avoided node may end a path."""
    spark = edges.sparkSession
    first = spark.createDataFrame([(0, source)], f"instance_id int, node {edges.schema['src'].dataType.simpleString()}")
    inner = edges.join(avoid.select(F.col("id").alias("src")).where(F.col("id") != F.lit(source)), "src", "left_anti").select("src", "dst")
    return distances(inner, first, max_depth).select("node", "d")


def to_target(edges: DataFrame, queries: DataFrame, max_depth: int) -> DataFrame:
    """(instance_id, node, d) distances to t."""
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return distances(back, queries.select("instance_id", F.col("t").alias("node")), max_depth)


def budget_subgraph(edges: DataFrame, queries: DataFrame, max_k: int) -> DataFrame:
    """(instance_id, src, dst, ord, d_s, d_t) of the edges on some walk s -> t of at most k edges, per query (instance_id, s, t, k)."""
    d_t = cut(to_target(edges, queries, max_k - 1))
    bound = d_t.select("instance_id", "node", F.col("d").alias("rest")).join(queries.select("instance_id", "k"), "instance_id")
    d_s = distances(edges, queries.select("instance_id", F.col("s").alias("node")), max_k - 1, bound=bound)
    a = d_s.select("instance_id", F.col("node").alias("src"), F.col("d").alias("d_s"))
    b = d_t.select("instance_id", F.col("node").alias("dst"), F.col("d").alias("d_t"))
    kept = edges.select("src", "dst", "ord").join(a, "src").join(b, ["instance_id", "dst"]).join(queries.select("instance_id", "k"), "instance_id")
    return kept.where("d_s + 1 + d_t <= k").select("instance_id", "src", "dst", "ord", "d_s", "d_t")


def viable_roots(edges: DataFrame, k: int) -> DataFrame:
    """(root): nodes that are the least node of some cycle of at most k edges' closed walk, by bounded search in the graph of larger nodes."""
    starts = edges.where("dst > src").select(F.col("src").alias("instance_id")).distinct().select("instance_id", F.col("instance_id").alias("node"))
    reach = distances(edges, starts, k - 1, within=F.col("dst") > F.col("instance_id"))
    back = edges.select(F.col("src").alias("node"), F.col("dst").alias("instance_id"))
    return reach.where("d > 0").join(back, ["node", "instance_id"], "left_semi").select(F.col("instance_id").alias("root")).distinct()


def cycle_subgraphs(edges: DataFrame, k: int) -> DataFrame:
    """(instance_id = root, src, dst, ord) for every viable root: edges among nodes >= root on a closed walk of at most k edges."""
    roots = cut(viable_roots(edges, k))
    q = roots.select(F.col("root").alias("instance_id"), F.col("root").alias("node"))
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    inside = F.col("dst") >= F.col("instance_id")
    d_t = cut(distances(back, q, k - 1, within=inside))
    d_s = distances(edges, q, k - 1, within=inside, bound=d_t.select("instance_id", "node", F.col("d").alias("rest"), F.lit(k).alias("k")))
    a = d_s.select("instance_id", F.col("node").alias("src"), F.col("d").alias("d_s"))
    b = d_t.select("instance_id", F.col("node").alias("dst"), F.col("d").alias("d_t"))
    return edges.select("src", "dst", "ord").join(a, "src").join(b, ["instance_id", "dst"]).where(F.col("d_s") + 1 + F.col("d_t") <= k).select("instance_id", "src", "dst", "ord")


def components(edges: DataFrame, directed: bool = False, max_rounds: int = MAX_ROUNDS) -> DataFrame:
    """(id, component): weakly connected, or strongly connected if directed; a component is named by its least node.

    Strongly connected ones by colouring: the least node that reaches a node colours it, and those of a colour that
    reach their colour's node are a component; the rest goes on. Every round is a join with one row per node; the rounds are as many as the longest
    shortest path has edges. Weakly connected ones take a logarithm of that. What has not settled after max_rounds raises an error.
    """
    if not directed:
        return _stars(edges, max_rounds)
    live = _trimmed(_spanned(edges.select("src", "dst")), max_rounds)
    every = edges.select(F.col("src").alias("id")).union(edges.select(F.col("dst").alias("id"))).distinct()
    nodes = cut(live.select(F.col("src").alias("id")).union(live.select(F.col("dst").alias("id"))).distinct())
    done = cut(every.join(nodes, "id", "left_anti").select("id", F.col("id").alias("component")))
    for _ in range(max_rounds):
        if is_empty(nodes):
            break
        colour = cut(_least_reaching(live, nodes, max_rounds))
        c1, c2 = colour.select(F.col("id").alias("src"), F.col("component").alias("c1")), colour.select(F.col("id").alias("dst"), F.col("component").alias("c2"))
        same = cut(live.join(c1, "src").join(c2, "dst").where("c1 = c2").select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("c1").alias("instance_id")))
        own = distances_in(same, colour.where("id = component").select(F.col("component").alias("instance_id"), F.col("id").alias("node")), max_rounds)
        found = cut(own.select(F.col("node").alias("id"), F.col("instance_id").alias("component")))
        done = done.unionByName(found)
        nodes = cut(nodes.join(found, "id", "left_anti"))
        keep = nodes.select("id")
        live = _trimmed(live.join(keep.select(F.col("id").alias("src")), "src", "left_semi").join(keep.select(F.col("id").alias("dst")), "dst", "left_semi").select("src", "dst"), max_rounds)
        left = live.select(F.col("src").alias("id")).union(live.select(F.col("dst").alias("id"))).distinct()
        alone = cut(nodes.join(left, "id", "left_anti").select("id", F.col("id").alias("component")))
        done, nodes = done.unionByName(alone), cut(left)
    else:
        if not is_empty(nodes):
            raise RuntimeError("components did not settle")
    return done


def _stars(edges: DataFrame, max_rounds: int) -> DataFrame:
    """(id, component) of weakly connected components: every node is tied to the least node around it, and again, until all hang on their least node."""
    every = edges.select(F.col("src").alias("id")).union(edges.select(F.col("dst").alias("id"))).distinct()
    cur = cut(edges.where("src <> dst").select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).distinct())
    seen = None
    for _ in range(max_rounds):
        around = cur.unionByName(cur.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = around.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        up = around.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = up.groupBy("a").agg(F.min("b").alias("m"))
        cur = cut(up.join(low, "a").select(F.when(F.col("b") == F.col("m"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b")).where("a <> b").distinct())
        state = tuple(cur.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError("components did not settle")
    tied = cur.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("component"))
    return every.join(tied, "id", "left").select("id", F.coalesce("component", "id").alias("component"))


def reduce_to_scc(edges: DataFrame) -> DataFrame:
    """The edges inside one strongly connected component: no others are on a cycle."""
    of = cut(components(edges, directed=True))
    a, b = of.select(F.col("id").alias("src"), F.col("component").alias("_a")), of.select(F.col("id").alias("dst"), F.col("component").alias("_b"))
    return edges.join(a, "src").join(b, "dst").where("_a = _b").select(*edges.columns)


SPAN_ROUNDS = 8  # of a reduction that is exact after any number of rounds


def _spanned(edges: DataFrame) -> DataFrame:
    """Edges without those whose ends' order keeps them off every cycle: a cycle leads up and down between its least and its largest node.

    So it lies between the least and the largest node of all edges that lead up, and of all that lead down. Chains that only rise or fall
    go at once, however long, of which trimming would take one node a round.
    """
    up, down = F.col("src") < F.col("dst"), F.col("src") > F.col("dst")
    seen = None
    for _ in range(SPAN_ROUNDS):
        ends = tuple(edges.agg(*[f(F.when(way, F.col(c))) for way, a, b in ((up, "src", "dst"), (down, "dst", "src")) for f, c in ((F.min, a), (F.max, b))]).first())
        if None in ends:
            return edges.where("false")
        span = (max(ends[0], ends[2]), min(ends[1], ends[3]))
        if span == seen:
            break
        seen = span
        edges = edges.where(F.col("src").between(*map(F.lit, span)) & F.col("dst").between(*map(F.lit, span)))
    return edges


def _trimmed(edges: DataFrame, max_rounds: int) -> DataFrame:
    """Edges without those that leave a node nothing enters or enter a node nothing leaves, again and again: such nodes are on no cycle."""
    live, n = cut(edges.distinct()), -1
    for _ in range(max_rounds):
        if live.count() == n:
            break
        n = live.count()  # a trim that ends early is a trim as well: the graph left is only larger
        heads, tails = live.select(F.col("dst").alias("src")).distinct(), live.select(F.col("src").alias("dst")).distinct()
        live = cut(live.join(heads, "src", "left_semi").join(tails, "dst", "left_semi").select("src", "dst"))
    return live


def distances_in(edges: DataFrame, sources: DataFrame, max_depth: int) -> DataFrame:
    """(instance_id, node) reachable from the sources over edges (instance_id, src, dst) of the same instance."""
    layer = cut(sources.select("instance_id", "node").distinct())
    seen = layer
    for _ in range(max_depth):
        nxt = layer.join(edges.withColumnRenamed("src", "node"), ["instance_id", "node"]).select("instance_id", F.col("dst").alias("node")).distinct()
        layer = cut(nxt.join(seen, ["instance_id", "node"], "left_anti"))
        if is_empty(layer):
            return seen
        seen = cut(seen.unionByName(layer))
    raise RuntimeError("the search did not end")


def _least_reaching(edges: DataFrame, nodes: DataFrame | None, max_rounds: int) -> DataFrame:
    """(id, component): the least node from which id is reached."""
    nodes = nodes if nodes is not None else edges.select(F.col("src").alias("id")).union(edges.select(F.col("dst").alias("id"))).distinct()
    best = cut(nodes.select("id", F.col("id").alias("component")))
    changed = best
    for _ in range(max_rounds):
        sent = changed.join(edges, changed["id"] == edges["src"]).groupBy(F.col("dst").alias("id")).agg(F.min("component").alias("new"))
        nxt = cut(best.join(sent, "id", "left").select("id", F.least("component", "new").alias("component"), (F.col("new") < F.col("component")).alias("moved")))
        best, changed = nxt.select("id", "component"), nxt.where("moved").select("id", "component")
        if is_empty(changed):
            return best
    raise RuntimeError("components did not settle")
