"""Cost, delay and accuracy measures of searches, one row per run, and their aggregates."""

from __future__ import annotations

import hashlib
import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hopbound.functions.search import Csr, Run, search

RUN = (
    "family string, instance_id long, scheme string, k int, n int, m int, outputs long, capped boolean, steps_search long, steps_cascade long, steps_output long, steps_bfs long, "
    "steps_seed long, intervals long, max_delay long, initial_delay long, terminal_delay long, amortized double, max_period long, calls long, wall_ns long, digest string"
)


def intervals(run: Run) -> list[int]:
    """Steps of each interval between events; the first counts from the start, the last ends the run."""
    at = [sum(e[1:]) for e in run.events if e[0] != "start"]
    return [b - a for a, b in zip([0, *at], at)]


def periods(run: Run) -> list[int]:
    return [b - a for a, b in zip([0, *run.phases], run.phases)]


def run_row(family: str, instance: int, scheme: str, k: int, csr: Csr, run: Run, wall: int) -> tuple:
    gaps = intervals(run)
    ends = np.cumsum(gaps)
    unit = (k + 1) * (csr.n + csr.m)
    amortized = max((e / ((p + 1) * unit) for p, e in enumerate(ends)), default=0.0)
    st = run.steps
    text = ";".join(">".join(str(csr.names[i]) for i in p) for p in run.outputs)
    return (family, instance, scheme, k, csr.n, csr.m, len(run.outputs), run.capped, st["search"], st["cascade"], st["output"], st["bfs"], st["seed"], len(gaps), max(gaps, default=0), gaps[0] if gaps else 0, gaps[-1] if gaps else 0, amortized, max(periods(run), default=0), run.calls, wall, hashlib.md5(text.encode()).hexdigest())


def measure(family: str, instance: int, csr: Csr, s, t, k: int, schemes: list[str], cap: int | None, passes: int = 1) -> list[tuple]:
    """A row per scheme over one instance; wall_ns is the least of the passes, which are separate for each scheme."""
    out = []
    a, b = csr.index(s), csr.index(t)
    if a is None or b is None:
        return out
    walls = dict.fromkeys(schemes, 1 << 62)
    runs: dict[str, Run] = {}
    for _ in range(passes):  # a pass goes through all schemes, so that passes of one are apart
        for scheme in schemes:
            begun = time.perf_counter_ns()
            runs[scheme] = search(csr, a, b, k, scheme, cap)
            walls[scheme] = min(walls[scheme], time.perf_counter_ns() - begun)
    return [run_row(family, instance, x, k, csr, runs[x], walls[x]) for x in schemes]


def _frame(rows: list[tuple]) -> pd.DataFrame:
    return pd.DataFrame(rows, columns=[c.split()[0] for c in RUN.split(", ")])


def measure_graph(queries: DataFrame, edges: list[tuple], family: str, schemes: list[str], cap: int | None = 100_000, passes: int = 1) -> DataFrame:
    """Runs of all queries (instance_id, s, t, k) over one shipped graph, in parallel over the queries."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        csr = Csr.of(edges)
        for b in batches:
            rows: list[tuple] = []
            for i, s, t, k in zip(b["instance_id"], b["s"].tolist(), b["t"].tolist(), b["k"]):
                rows += measure(family, int(i), csr, s, t, int(k), schemes, cap, passes)
            yield _frame(rows)

    return queries.select("instance_id", "s", "t", "k").mapInPandas(run, RUN)


def measure_generated(instances: DataFrame, make, family: str, schemes: list[str], cap: int | None = 100_000, passes: int = 1) -> DataFrame:
    """Runs of instances (instance_id, k), each on the graph make(instance_id, k) -> (edges, s, t) builds in the task."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows: list[tuple] = []
            for i, k in zip(b["instance_id"], b["k"]):
                edges, s, t = make(int(i), int(k))
                rows += measure(family, int(i), Csr.of(edges, (s, t)), s, t, int(k), schemes, cap, passes)
            yield _frame(rows)

    return instances.select("instance_id", "k").mapInPandas(run, RUN)


def _pairs(runs: DataFrame, a: str, b: str) -> DataFrame:
    """Uncapped runs of two schemes side by side."""
    cols = ["outputs", "intervals", "steps_search", "steps_cascade", "steps_output", "calls", "wall_ns"]
    both = [runs.where((F.col("scheme") == s) & ~F.col("capped")).select("family", "instance_id", "k", *[F.col(c).alias(f"{p}_{c}") for c in cols]) for s, p in ((a, "a"), (b, "b"))]
    return both[0].join(both[1], ["family", "instance_id", "k"])


def _steps(p: str):
    return F.col(f"{p}_steps_search") + F.col(f"{p}_steps_cascade") + F.col(f"{p}_steps_output")


def loss(runs: DataFrame, of: str = "guarded", against: str = "tight") -> DataFrame:
    """Per family and k: share of paths lost, share of instances that lose any, instances, and those excluded by the cap."""
    capped = runs.where(F.col("scheme") == against).groupBy("family", "k").agg(F.count_if("capped").alias("excluded"))
    g = _pairs(runs, against, of).groupBy("family", "k").agg(F.count(F.lit(1)).alias("instances"), F.sum("a_outputs").alias("paths"), F.sum(F.col("a_outputs") - F.col("b_outputs")).alias("missed"), F.round(F.avg((F.col("b_outputs") < F.col("a_outputs")).cast("int")), 4).alias("losing_share"))
    return g.join(capped, ["family", "k"]).withColumn("loss", F.round(F.when(F.col("paths") > 0, F.col("missed") / F.col("paths")).otherwise(0.0), 4))


def step_ratio(runs: DataFrame, of: str = "tight", against: str = "guarded") -> DataFrame:
    """Per family and k: steps per interval of one scheme over those of another; sums over sums, and the median of instances.

    calls_ratio is the other way round; with targets, each output of either scheme also counts as a call, as
    where a call is opened at the target.
    """
    one = (_steps("a") / F.col("a_intervals")) / (_steps("b") / F.col("b_intervals"))
    return _pairs(runs, of, against).groupBy("family", "k").agg(F.round((F.sum(_steps("a")) / F.sum("a_intervals")) / (F.sum(_steps("b")) / F.sum("b_intervals")), 4).alias("ratio"), F.round(F.median(one), 4).alias("median_ratio"), F.round(F.sum("b_calls") / F.sum("b_intervals") / (F.sum("a_calls") / F.sum("a_intervals")), 4).alias("calls_ratio"), F.round((F.sum("b_calls") + F.sum("b_outputs")) / F.sum("b_intervals") / ((F.sum("a_calls") + F.sum("a_outputs")) / F.sum("a_intervals")), 4).alias("calls_ratio_with_targets"))


def excess_by_account(runs: DataFrame, of: str = "tight", against: str = "guarded") -> DataFrame:
    """Per family and k: what each account has more of in one scheme than in the other, as a share of all steps of the other; the three add up to the net excess."""
    each = [F.round((F.sum(f"a_steps_{x}") - F.sum(f"b_steps_{x}")) / F.sum(_steps("b")), 4).alias(x) for x in ("search", "cascade", "output")]
    net = F.round(F.sum(_steps("a")) / F.sum(_steps("b")) - 1, 4).alias("net")
    return _pairs(runs, of, against).groupBy("family", "k").agg(*each, net)


def missed(paths: DataFrame, against: DataFrame, keys: list[str]) -> DataFrame:
    """The paths (keys, seq, path_str) of one search that another does not report: an anti-join."""
    return paths.join(against.select(*keys, "path_str"), [*keys, "path_str"], "left_anti").select(*keys, "seq", "path_str")


def order_breaks(paths: DataFrame, against: DataFrame, keys: list[str]) -> DataFrame:
    """(strangers, inversions): reported paths that the complete search does not have, and neighbours in the wrong order; 0 and 0 if `against` is a subsequence."""
    both = against.select(*keys, "path_str", F.col("seq").alias("_b")).join(paths.select(*keys, "path_str", F.col("seq").alias("_a")), [*keys, "path_str"], "left")
    w = Window.partitionBy(*keys).orderBy("_b")
    return both.withColumn("_before", F.lag("_a").over(w)).agg(F.count_if(F.col("_a").isNull()).alias("strangers"), F.count_if(F.col("_before") >= F.col("_a")).alias("inversions"))


def wallclock_ratio(runs: DataFrame, of: str = "tight", against: str = "guarded") -> DataFrame:
    return _pairs(runs, of, against).groupBy("family", "k").agg(F.round((F.sum("a_wall_ns") / F.sum("a_intervals")) / (F.sum("b_wall_ns") / F.sum("b_intervals")), 3).alias("wall_ratio"))


def delays(runs: DataFrame) -> DataFrame:
    """Per family, scheme and k: the largest delay, initial and terminal interval, amortized cost and period, over (k+1)(n+m)."""
    unit = (F.col("k") + 1) * (F.col("n") + F.col("m"))
    top = lambda c: F.round(F.max(F.col(c) / unit), 4)
    return runs.where("not capped").groupBy("family", "scheme", "k").agg(F.max("intervals").alias("most_intervals"), top("max_delay").alias("delay"), top("initial_delay").alias("initial"), top("terminal_delay").alias("terminal"), F.round(F.max("amortized"), 4).alias("amortized"), top("max_period").alias("period"))


def bound_violations(runs: DataFrame) -> DataFrame:
    """Runs of the tight scheme that exceed a proven bound; all columns should be 0."""
    unit = (F.col("k") + 1) * (F.col("n") + F.col("m"))
    c = lambda x: F.count_if(x).alias
    return runs.where("scheme = 'tight' and not capped").agg(
        c(F.col("max_delay") > 3 * unit)("over_delay"), c(F.col("initial_delay") > unit)("over_initial"), c(F.col("terminal_delay") > 2 * unit)("over_terminal"), c(F.col("amortized") > 2)("over_amortized"), c(F.col("max_period") > 2 * unit)("over_period")
    )


def harness_ns(times: int = 20_000) -> float:
    """What the clock calls around a search add to its time, in nanoseconds: the least of several means."""
    least = float("inf")
    for _ in range(5):
        begun = time.perf_counter_ns()
        for _ in range(times):
            time.perf_counter_ns()
        least = min(least, (time.perf_counter_ns() - begun) / times)
    return least


def counters(csr: Csr, s: int, t: int, k: int, scheme: str, hub: int) -> dict[str, int]:
    """Calls, entries of one node, and barrier writes by kind of one logged search."""
    run = search(csr, s, t, k, scheme, log=True)
    kinds = [w[1] for w in run.writes]
    return {"calls": run.calls, "hub_entries": sum(e[0] == hub for e in run.entries), "hub_entries_between": sum(e[0] == hub and e[2] == 1 for e in run.entries), **{k: kinds.count(k) for k in ("raise", "drop", "fruitful")}}
