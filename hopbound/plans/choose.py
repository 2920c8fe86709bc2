"""A small planner: picks a physical strategy for bounded path queries from counts, before anything is enumerated."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopbound.functions.search import COMPLETE
from hopbound.operators.labels import budget_subgraph
from hopbound.operators.paths import DIRECT_ROWS, search_groups, simple_paths

MAX_TASK_EDGES = 2_000_000
MIN_INSTANCES = 16
MANY_EDGES = 200_000


@dataclass
class Plan:
    strategy: str
    scheme: str
    cap: int | None
    reason: str
    instances: int
    largest: int

    def explain(self) -> str:
        return f"{self.strategy} ({self.scheme}, cap {self.cap}): {self.reason}; {self.instances} queries, largest reduced graph {self.largest} edges"


def choose(reduced: DataFrame, scheme: str = "tight", cap: int | None = None) -> Plan:
    """reduced: the budget subgraphs (instance_id, ...) of all queries. What an incomplete scheme finds depends on the whole of its search, so it always has one task a query."""
    per = reduced.groupBy("instance_id").agg(F.count(F.lit(1)).alias("m"))
    n, top = per.agg(F.count(F.lit(1)), F.coalesce(F.max("m"), F.lit(0))).first()
    if top > MAX_TASK_EDGES and scheme in COMPLETE:
        return Plan("relational", scheme, cap, "a reduced graph is too large for a task", n, top)
    if n < MIN_INSTANCES and top > MANY_EDGES and scheme in COMPLETE:
        return Plan("split", scheme, cap, "few queries over large graphs", n, top)
    return Plan("task", scheme, cap, "every reduced graph fits a task", n, top)


def run_planned(edges: DataFrame, queries: DataFrame, max_k: int, scheme: str = "tight", cap: int | None = None) -> DataFrame:
    """(instance_id, len, path) by the chosen strategy."""
    n = queries.limit(DIRECT_ROWS + 1).count()
    if n and n * edges.limit(DIRECT_ROWS // n + 1).count() <= DIRECT_ROWS:
        return simple_paths(edges, queries, max_k, "tight_seeded" if scheme == "tight" else scheme, "direct", cap).select("instance_id", "len", "path")
    reduced = budget_subgraph(edges, queries, max_k)
    plan = choose(reduced, scheme, cap)
    if plan.strategy == "task":
        rows = reduced.join(queries, "instance_id")
        found = search_groups(rows, queries.schema["instance_id"].dataType.simpleString(), edges.schema["src"].dataType.simpleString(), scheme, cap)
    else:
        found = simple_paths(edges, queries, max_k, scheme, plan.strategy, cap)
    return found.select("instance_id", "len", "path")
