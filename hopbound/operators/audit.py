"""Checks of the searches' invariants, relationally over paths and logs; all counts should be 0 for the complete schemes."""

from __future__ import annotations

from collections import Counter

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hopbound.functions.search import Csr, Run, distances_to, search


def audit_outputs(paths: DataFrame, edges: DataFrame, queries: DataFrame) -> DataFrame:
    """Paths that are not simple, too long, repeated, have wrong ends, or use an edge that is not there."""
    p = paths.join(queries, "instance_id")
    inner = F.slice("path", 1, F.size("path") - 1)
    bad = p.agg(
        F.count_if((F.size(F.array_distinct(inner)) < F.size(inner)) | ((F.col("s") != F.col("t")) & F.array_contains(inner, F.col("t")))).alias("not_simple"),
        F.count_if(F.col("len") > F.col("k")).alias("too_long"),
        F.count_if((F.element_at("path", 1) != F.col("s")) | (F.element_at("path", -1) != F.col("t"))).alias("wrong_ends"),
        (F.count(F.lit(1)) - F.countDistinct("instance_id", "path")).alias("repeated"),
    )
    hops = p.select(F.inline(F.transform(F.sequence(F.lit(1), F.size("path") - 1), lambda i: F.struct(F.element_at("path", i).alias("src"), F.element_at("path", i + 1).alias("dst")))))
    missing = hops.distinct().join(edges.select("src", "dst"), ["src", "dst"], "left_anti").agg(F.count(F.lit(1)).alias("no_edge"))
    return bad.crossJoin(missing)


def edge_violations(edges: DataFrame, barriers: DataFrame, on_path: DataFrame) -> DataFrame:
    """Off-path edges whose source has a barrier more than one above its target's; barriers: (node, b), on_path: (id)."""
    off = edges.select("src", "dst").join(on_path.select(F.col("id").alias("src")), "src", "left_anti").join(on_path.select(F.col("id").alias("dst")), "dst", "left_anti")
    a, b = barriers.select(F.col("node").alias("src"), F.col("b").alias("bs")), barriers.select(F.col("node").alias("dst"), F.col("b").alias("bd"))
    return off.join(a, "src").join(b, "dst").where("bs > bd + 1")


def write_chains(writes: DataFrame) -> DataFrame:
    """Longest runs per node of raises without a drop between, and drops without a raise or fruitful write between, from (seq, node, kind)."""
    w = Window.partitionBy("node").orderBy("seq")
    up = writes.where("kind <> 'fruitful'")
    flag = up.withColumn("turn", F.coalesce((F.col("kind") != F.lag("kind").over(w)).cast("int"), F.lit(1)))
    island = flag.withColumn("run", F.sum("turn").over(w))
    return island.groupBy("node", "kind", "run").agg(F.count(F.lit(1)).alias("n")).groupBy("kind").agg(F.max("n").alias("longest"))


def run_violations(csr: Csr, s: int, t: int, k: int, scheme: str = "tight") -> Counter:
    """Counts of broken invariants of one logged run (see the keys); small graphs only."""
    run: Run = search(csr, s, t, k, scheme, log=True, audit=True)
    bad = Counter(run.violations)
    # one entry per node and depth in a phase, two in an interval
    bad["entries_per_phase"] = sum(n > 1 for n in Counter(run.entries).values())
    bad["entries_per_interval"] = sum(n > 2 for n in Counter(e[:3] for e in run.entries).values())
    bad["calls_per_phase"] = sum(n > k for n in Counter((e[0], *e[2:]) for e in run.entries).values())
    chain: Counter = Counter()
    raises: Counter = Counter()
    for node, kind, old, new, _, _ in run.writes:
        if kind == "raise":
            raises[node] += 1
            chain[node] = 0
            bad["raise_not_higher"] += new <= old
            bad["raise_chain"] += raises[node] > k
        elif kind == "drop":
            raises[node] = 0
            chain[node] += 1
            bad["drop_not_lower"] += new >= old
            bad["drop_chain"] += chain[node] > max(1, k - 1)
        else:
            chain[node] = 0
            bad["fruitful_lowers"] += new < old
    bad["target_written"] = sum(w[0] == t for w in run.writes) if s != t else 0
    return bad


def relative(csr: Csr, outside: bytearray | list[int], z: int) -> list[float]:
    """Distance of every node to z over paths whose inner nodes are off `outside` (flags); the ends may be on it."""
    far = csr.n + 1
    d, _ = distances_to(csr, z, csr.n, outside)
    return [float("inf") if x > csr.n else x for x in (d[v] if not outside[v] or v == z else 1 + min((d[w] for w in csr.succ[v] if w == z or not outside[w]), default=far) for v in range(csr.n))]


def triangle_violations(csr: Csr, outside: list[int]) -> int:
    """Triples x, y, z, y off the set, with dist(x, z) > dist(x, y) + dist(y, z)."""
    to = [relative(csr, outside, z) for z in range(csr.n)]
    return sum(to[z][x] > to[y][x] + to[z][y] for y in range(csr.n) if not outside[y] for x in range(csr.n) for z in range(csr.n))


TIGHT_CHECKS = (
    "pruning", "guard", "start_or_target_written", "fruitful_value", "fruitless_raises", "fruitless_falls", "cascade_once", "cascade_value", "cascade_bound", "cascade_reach", "repair_leaves", "call_lowers", "call_complete",
    "call_preserves", "fruitful_without_output", "descent_call_fruitful", "descent_call_outlives", "origin_off_spine", "origin_twice", "entered_after_drop", "entries_per_phase", "entries_per_interval", "calls_per_phase", "fruitless_per_period", "start_raises", "start_drops",
)


class Lemmas:
    """Watches one search of a small graph and counts, at every call, what breaks a proven property. The names of the properties are the keys of `bad`.

    closure and registered are those of the schemes that reset: predecessors of reset nodes are reset, and raised nodes wait at all their successors.
    """

    def __init__(self, csr: Csr, s: int, t: int, k: int):
        self.csr, self.s, self.t, self.k = csr, s, t, min(k, csr.n)
        self.bad: Counter = Counter()
        self.open: list[tuple[list[int], int, int, int]] = []  # barriers at entry, writes, outputs and log entries before it
        self.log: list[tuple] = []
        self.outputs: list[tuple[int, ...]] = []
        self.dropped: set[int] = set()
        self.origins: set[int] = set()
        self.mark = 0

    def output(self, path: tuple[int, ...]) -> None:
        self.outputs.append(path)
        self.log.append(("output",))
        self.dropped.clear()
        self.origins.clear()

    def entered(self, state, path: list[int]) -> None:
        csr, b, on, t, k = self.csr, state.b, state.on, self.t, self.k
        v, h = path[-1], len(path) - 1
        self.bad["guard"] += h > 0 and b[v] > k - h
        self.bad["start_or_target_written"] += b[self.s] != 0 or b[t] != 0
        d, _ = distances_to(csr, t, k, on)
        self.bad["pruning"] += sum((w == t or not on[w]) and d[w] + h + 1 <= k and b[w] + h >= k for w in csr.succ[v])
        self._registered(state)
        self.open.append((list(b), len(state.run.writes), len(self.outputs), len(self.log)))
        self.log.append(("enter", v, h, v in self.dropped))

    def closing(self, state, path: list[int], found: int) -> None:
        csr, b, on, t, k = self.csr, state.b, state.on, self.t, self.k
        v, h = path[-1], len(path) - 1
        before, writes, outputs, _ = self.open[-1]
        self.mark = len(state.run.writes)
        if found <= k:
            d, _ = distances_to(csr, t, k, on)
            true = 1 + min((d[w] for w in csr.succ[v] if w == t or not on[w]), default=k + 1)
            self.bad["fruitful_value"] += found != true or found > k - h
            self.bad["fruitful_without_output"] += len(self.outputs) == outputs
            self.bad["origin_off_spine"] += not self.outputs or self.outputs[-1][: h + 1] != tuple(path)
            self.bad["origin_twice"] += v in self.origins
            self.origins.add(v)
        else:
            self.bad["fruitless_raises"] += k - h + 1 <= before[v]
            self.bad["fruitless_falls"] += any(w[1] != "raise" for w in state.run.writes[writes:]) or any(x < y for x, y in zip(b, before))
        want = self._completions(v, k - h, [x for x in path[:-1]])
        self.bad["call_complete"] += [p[h:] for p in self.outputs[outputs:]] != want

    def _completions(self, v: int, budget: int, avoid: list[int]) -> list[tuple[int, ...]]:
        """All ways from v to the target within the budget around the nodes to avoid, by plain recursion."""
        out = []
        for w in self.csr.succ[v] if budget > 0 else ():
            if w == self.t:
                out.append((v, w))
            elif w != v and w not in avoid:
                out += [(v, *rest) for rest in self._completions(w, budget - 1, [*avoid, v])]
        return out

    def repaired(self, state, path: list[int], found: int) -> None:
        csr, b, on, t, k = self.csr, state.b, state.on, self.t, self.k
        v = path[-1]
        new = state.run.writes[self.mark :]
        if found > k:
            return
        drops = [w for w in new if w[1] == "drop"]
        self.dropped.update(w[0] for w in drops)
        self.bad["cascade_once"] += len({w[0] for w in drops}) != len(drops)
        to_v, _ = distances_to(csr, v, csr.n, on)
        without = bytearray(on)
        without[v] = 0
        to_t, _ = distances_to(csr, t, k, without)
        self.bad["cascade_value"] += sum(w[3] != found + to_v[w[0]] for w in drops)
        self.bad["cascade_bound"] += sum(w[3] < to_t[w[0]] for w in drops)
        self.bad["cascade_reach"] += sum(b[x] > found + to_v[x] for x in range(csr.n) if not on[x] and x != t and to_v[x] <= csr.n)
        self.bad["repair_leaves"] += sum(b[x] > b[y] + 1 for x in range(csr.n) for y in csr.succ[x] if x != v and x != t and not without[x] and not without[y])
        reset = {w[0] for w in new if w[3] == 0}
        self.bad["closure"] += sum(not on[x] and x != t and b[x] != 0 for y in reset for x in csr.pred[y])

    def closed(self, state, path: list[int], v: int, found: int) -> None:
        csr, b, on = self.csr, state.b, state.on
        before, _, _, at = self.open.pop()
        self.bad["call_lowers"] += any(x < y for x, y in zip(b, before))
        self.bad["call_preserves"] += bool(path) and sum(b[x] > b[y] + 1 for x in range(csr.n) for y in csr.succ[x] if x != self.t and not on[x] and (not on[y] or y == self.t))
        self.log.append(("fruitful" if found <= self.k else "fruitless", v, at))
        self._registered(state)

    def _registered(self, state) -> None:
        waiting = getattr(state, "waiting", None)
        if waiting is not None:
            self.bad["registered"] += sum(x not in waiting[w] for x in range(self.csr.n) if not state.on[x] and state.b[x] > 0 for w in self.csr.succ[x])

    def finish(self, writes: list[tuple]) -> Counter:
        """Adds what can be told only in the end: phases, and writes at the start."""
        cuts = [i for i, e in enumerate(self.log) if e[0] == "output"]
        phase = [0] * len(self.log)  # even: ascents, odd: descents; a period is an ascent and the descent after it
        for n, (at, end) in enumerate(zip(cuts, [*cuts[1:], len(self.log)]), 1):
            fruitful = [i for i in range(at, end) if self.log[i][0] == "fruitful"]
            last = fruitful[-1] if fruitful else at
            for i in range(at, end):
                phase[i] = 2 * n - 1 if i <= last else 2 * n
        close = {e[2]: (i, e[0]) for i, e in enumerate(self.log) if e[0].startswith("fruit")}
        per_phase, per_interval, calls, fruitless = Counter(), Counter(), Counter(), Counter()
        outputs = 0
        for i, e in enumerate(self.log):
            outputs += e[0] == "output"
            if e[0] == "enter":
                per_phase[e[1], e[2], phase[i]] += 1
                per_interval[e[1], e[2], outputs] += 1
                calls[e[1], phase[i]] += 1
                self.bad["entered_after_drop"] += phase[i] % 2 and e[3]
                if phase[i] % 2 and i in close:
                    self.bad["descent_call_fruitful"] += close[i][1] == "fruitful"
                    self.bad["descent_call_outlives"] += phase[close[i][0]] != phase[i]
            elif e[0] == "fruitless":
                fruitless[e[1], (phase[i] + 1) // 2] += 1
        self.bad["entries_per_phase"] += sum(n > 1 for n in per_phase.values())
        self.bad["entries_per_interval"] += sum(n > 2 for n in per_interval.values())
        self.bad["calls_per_phase"] += sum(n > self.k for n in calls.values())
        self.bad["fruitless_per_period"] += sum(n > self.k for n in fruitless.values())
        self.bad["start_raises"] += sum(w[0] == self.s and w[1] == "raise" for w in writes) > 1
        self.bad["start_drops"] += sum(w[0] == self.s and w[1] == "drop" for w in writes)
        return self.bad


def lemma_violations(csr: Csr, s: int, t: int, k: int, scheme: str = "tight") -> Counter:
    """Counts of broken properties of one search; small graphs only."""
    watch = Lemmas(csr, s, t, k)
    run = search(csr, s, t, k, scheme, watch=watch)
    return watch.finish(run.writes)
