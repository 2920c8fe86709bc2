"""Depth-first search for simple paths of bounded length, pruned by node barriers. No Spark in here.

A node's barrier is a lower bound of what is left to the target from there, given the path so far; a successor is
tried only while depth and barrier leave room in the budget. Schemes differ in what they do to barriers when a
frame closes. Steps are counted by account: `search` (entries and scans), `cascade` (barrier repair), `output`
(nodes written), `bfs` (distance searches of the fresh schemes) and `seed` (the seeding search).
"""

from __future__ import annotations

from collections import deque
from collections.abc import Callable, Iterable, Iterator, Sequence
from dataclasses import dataclass, field

COMPLETE = ("tight", "tight_seeded", "loose", "lazy", "trivial", "fresh", "fresh_mutating")
INCOMPLETE = ("guarded", "lazy_tight")
UNBOUNDED = ("circuit", "backtrack")
SCHEMES = COMPLETE + INCOMPLETE + UNBOUNDED


@dataclass
class Csr:
    """Successors in scan order and predecessors, by dense node number."""

    names: list
    succ: list[list[int]]
    pred: list[list[int]]

    @classmethod
    def of(cls, edges: Iterable[tuple], extra: Iterable = ()) -> Csr:
        """From (src, dst) or (src, dst, ord) rows: loops and repeats are dropped, ord (else dst) is the scan order."""
        first: dict = {}
        for e in edges:
            a, b, o = e if len(e) == 3 else (*e, e[1])
            if a is None or b is None or a == b:
                continue
            if (a, b) not in first or o < first[a, b]:
                first[a, b] = o
        names = sorted({x for ab in first for x in ab} | set(extra))
        at = {x: i for i, x in enumerate(names)}
        succ: list[list[int]] = [[] for _ in names]
        pred: list[list[int]] = [[] for _ in names]
        for (a, b), _ in sorted(first.items(), key=lambda x: (at[x[0][0]], x[1], at[x[0][1]])):
            succ[at[a]].append(at[b])
            pred[at[b]].append(at[a])
        return cls(names, succ, pred)

    @property
    def n(self) -> int:
        return len(self.names)

    @property
    def m(self) -> int:
        return sum(map(len, self.succ))

    def index(self, name) -> int | None:
        try:
            return self._at[name]
        except AttributeError:
            self._at = {x: i for i, x in enumerate(self.names)}
            return self._at.get(name)
        except KeyError:
            return None


    def around(self, r: int, k: int) -> Csr | None:
        """The graph of nodes from r on that lie on a closed walk of at most k edges through r; None if there is none."""
        ahead, back = _layers(self.succ, r, k - 1), _layers(self.pred, r, k - 1)
        kept = [(x, y) for x, d in ahead.items() for y in self.succ[x] if y in back and d + 1 + back[y] <= k]
        if not kept:
            return None
        return Csr.of((self.names[x], self.names[y], i) for i, (x, y) in enumerate(kept))  # kept in scan order within x


def _layers(nexts: list[list[int]], r: int, depth: int) -> dict[int, int]:
    """Distances up to depth from r over nodes not before it."""
    d, wave = {r: 0}, [r]
    for h in range(1, depth + 1):
        ahead = []
        for x in wave:
            for y in nexts[x]:
                if y > r and y not in d:
                    d[y] = h
                    ahead.append(y)
        wave = ahead
    return d


@dataclass
class Run:
    """What one search found and what it cost."""

    outputs: list[tuple[int, ...]] = field(default_factory=list)
    events: list[tuple[str, int, int, int, int]] = field(default_factory=list)  # kind, search, cascade, output, bfs so far
    phases: list[int] = field(default_factory=list)  # total steps at the end of each period
    writes: list[tuple[int, str, int, int, int, int]] = field(default_factory=list)  # node, kind, old, new, depth, outputs so far
    entries: list[tuple[int, int, int, int]] = field(default_factory=list)  # node, depth, outputs so far, 1 in a descent
    steps: dict[str, int] = field(default_factory=dict)
    calls: int = 0
    capped: bool = False
    found: int = 0  # outputs so far, kept or not
    violations: dict[str, int] = field(default_factory=dict)

    @property
    def total(self) -> int:
        return sum(v for k, v in self.steps.items() if k != "seed")


def distances_to(csr: Csr, t: int, limit: int, skip: Sequence[int] = ()) -> tuple[list[int], int]:
    """(distance to t of every node, limit + 1 where it is more or none; steps). Nodes flagged in skip are not passed."""
    far = limit + 1
    d = [far] * csr.n
    d[t] = 0
    todo, steps = deque([t]), 0
    while todo:
        x = todo.popleft()
        if d[x] >= limit:
            continue
        steps += 1 + len(csr.pred[x])
        for p in csr.pred[x]:
            if d[p] == far and not (skip and skip[p]):
                d[p] = d[x] + 1
                todo.append(p)
    return d, steps


class _Barriers:
    """State shared by the schemes: barriers, who is on the path, the repair account and the log."""

    def __init__(self, csr: Csr, k: int, t: int, run: Run, log: bool):
        self.csr, self.k, self.t, self.run, self.log = csr, k, t, run, log
        self.b = [0] * csr.n
        self.on = bytearray(csr.n)
        self.cost = 0
        self.extra = 0  # search steps charged by a scheme
        self.depth = 0

    def write(self, x: int, value: int, kind: str) -> None:
        if self.log:
            self.run.writes.append((x, kind, self.b[x], value, self.depth, self.run.found))
        self.b[x] = value

    def fruitless(self, v: int, h: int) -> None:
        self.write(v, self.k - h + 1, "raise")

    def fruitful(self, v: int, near: int) -> None:
        raise NotImplementedError


class Tight(_Barriers):
    """The found distance is written, then exact distances flow back over off-path predecessors, nearest first."""

    def fruitful(self, v: int, near: int) -> None:
        b, on, pred = self.b, self.on, self.csr.pred
        self.write(v, near, "fruitful")
        wave, d = [v], near
        while wave:
            d += 1
            ahead = []
            for x in wave:
                self.cost += 1 + len(pred[x])
                for p in pred[x]:
                    if b[p] > d and not on[p]:
                        self.write(p, d, "drop")
                        ahead.append(p)
            wave = ahead


class Trivial(_Barriers):
    """Barriers stay 0: plain search cut at the budget."""

    def fruitless(self, v: int, h: int) -> None:
        pass

    def fruitful(self, v: int, near: int) -> None:
        pass


class Loose(_Barriers):
    """The whole off-path cone behind a fruitful node falls to 0."""

    def fruitful(self, v: int, near: int) -> None:
        b, on, pred = self.b, self.on, self.csr.pred
        self.write(v, 0, "fruitful")
        todo = deque([v])
        while todo:
            x = todo.popleft()
            self.cost += 1 + len(pred[x])
            for p in pred[x]:
                if b[p] and not on[p]:
                    self.write(p, 0, "drop")
                    todo.append(p)


class Lazy(_Barriers):
    """Failed nodes register with their successors; a fruitful node clears those registered with it, and so on."""

    def __init__(self, *a):
        super().__init__(*a)
        self.waiting: list[dict[int, None]] = [{} for _ in range(self.csr.n)]

    def fruitless(self, v: int, h: int) -> None:
        super().fruitless(v, h)
        for w in self.csr.succ[v]:
            self.waiting[w][v] = None
            self.extra += 1

    def lowered(self, x: int, value: int) -> int | None:
        """The value to write at a registered node, None to leave it."""
        return 0 if self.b[x] > 0 else None

    def fruitful(self, v: int, near: int) -> None:
        self.release(v, 0)

    def release(self, v: int, value: int) -> None:
        self.write(v, value, "fruitful")
        self.cost += 1 + len(self.waiting[v])
        open_lists = [(v, iter(list(self.waiting[v])), value)]
        while open_lists:
            x, rest, at = open_lists[-1]
            for u in rest:
                if not self.on[u] and (new := self.lowered(u, at + 1)) is not None:
                    self.write(u, new, "drop")
                    self.cost += 1 + len(self.waiting[u])
                    open_lists.append((u, iter(list(self.waiting[u])), new))
                    break
            else:
                self.waiting[x].clear()
                open_lists.pop()


class LazyTight(Lazy):
    """Registration as in Lazy, but distances are deposited along the registrations. A reconstruction; it can lose paths."""

    def lowered(self, x: int, value: int) -> int | None:
        return value if self.b[x] > value else None

    def fruitful(self, v: int, near: int) -> None:
        self.release(v, min(near, self.b[v]))


class Guarded(_Barriers):
    """The update runs only where it lowers a barrier, from the fruitful node on. It can lose paths."""

    def fruitful(self, v: int, near: int) -> None:
        b, on, pred = self.b, self.on, self.csr.pred
        if b[v] <= near:
            return
        self.write(v, near, "drop")
        self.cost += 1 + len(pred[v])
        trail = [(iter(pred[v]), near + 1)]
        while trail:
            rest, d = trail[-1]
            for p in rest:
                if b[p] > d and not on[p]:
                    self.write(p, d, "drop")
                    self.cost += 1 + len(pred[p])
                    trail.append((iter(pred[p]), d + 1))
                    break
            else:
                trail.pop()


_POLICY = {"tight": Tight, "tight_seeded": Tight, "trivial": Trivial, "loose": Loose, "lazy": Lazy, "lazy_tight": LazyTight, "guarded": Guarded}


def search(csr: Csr, s: int, t: int, k: int, scheme: str = "tight", cap: int | None = None, log: bool = False, audit: bool = False, seed: Sequence[int] | None = None, max_steps: int | None = None, watch=None) -> Run:
    """All simple s-t paths of at most k edges in lexicographic scan order; s = t gives the cycles through s.

    cap stops after so many outputs and max_steps after so many scans and entries (both flagged as capped). log keeps barrier writes and entries; audit counts violations of the
    barrier invariants at every entry and close (slow). seed are known distances to t, else a search finds them. watch is told of entries, closes and repairs (see audit.Lemmas).
    """
    if scheme in UNBOUNDED:
        return _unbounded(csr, s, t, scheme, cap)
    if scheme in ("fresh", "fresh_mutating"):
        return _fresh(csr, s, t, k, scheme == "fresh_mutating", cap)
    run = Run()
    for _ in _explore(run, csr, s, t, k, scheme, cap, log, audit, seed, max_steps, watch, True):
        pass
    return run


def stream(csr: Csr, s: int, t: int, k: int, scheme: str = "tight", cap: int | None = None) -> Iterator[tuple[tuple[int, ...], int]]:
    """(path, steps until it) one by one as they are found, in the order of search; nothing is kept, so memory is that of the barriers and the path."""
    if scheme not in _POLICY:
        run = search(csr, s, t, k, scheme, cap)
        yield from zip(run.outputs, [sum(e[1:]) for e in run.events if e[0] == "output"] or [0] * len(run.outputs))
        return
    run = Run()
    for path in _explore(run, csr, s, t, k, scheme, cap, False, False, None, None, None, False):
        yield path, _total(run.events[-1])


def _explore(run: Run, csr: Csr, s: int, t: int, k: int, scheme: str, cap: int | None, log: bool, audit: bool, seed: Sequence[int] | None, max_steps: int | None, watch, keep: bool) -> Iterator[tuple[int, ...]]:
    """The search itself: yields every output; run is filled on the way, its outputs and events only if keep."""
    k = min(k, csr.n)
    state: _Barriers = _POLICY[scheme](csr, k, t, run, log or watch is not None)
    seeding = 0
    if scheme == "tight_seeded":
        known, seeding = (list(seed), 0) if seed is not None else distances_to(csr, t, k)
        state.b[:] = [min(x, k + 1) for x in known]
        state.b[t] = 0
    b, on, succ = state.b, state.on, csr.succ
    outputs, events = run.outputs, run.events
    looked = written = 0
    period_end = -1  # steps at the last fruitful close since the last output
    dropping = 0

    def tell(kind: str) -> None:
        if not keep:
            events.clear()
        events.append((kind, looked + state.extra, state.cost, written, 0))

    if k <= 0:
        run.steps = dict.fromkeys(("search", "cascade", "output", "bfs", "seed"), 0)
        return
    path, cursor, best = [s], [0], [k + 1]
    on[s] = 1
    looked, run.calls = 1, 1
    tell("start")
    if log:
        run.entries.append((s, 0, 0, 0))
    if watch is not None:
        watch.entered(state, path)
    while path:
        v, h = path[-1], len(path) - 1
        nexts = succ[v]
        i = cursor[-1]
        child = -1
        while i < len(nexts):
            w = nexts[i]
            i += 1
            looked += 1
            if b[w] + h >= k:
                continue
            if w == t:
                best[-1] = 1
                written += h + 2
                if run.found and keep:
                    run.phases.append(period_end if period_end >= 0 else _total(events[-1]))
                run.found += 1
                out = (*path, t)
                if keep:
                    outputs.append(out)
                tell("output")
                if watch is not None:
                    watch.output(out)
                yield out
                period_end, dropping = -1, 1
                if cap is not None and run.found >= cap:
                    run.capped = True
                    break
            elif not on[w]:
                child = w
                break
        cursor[-1] = i
        if run.capped:
            break
        if max_steps is not None and looked > max_steps:
            run.capped = True
            break
        if child >= 0:
            path.append(child)
            cursor.append(0)
            best.append(k + 1)
            on[child] = 1
            looked += 1
            run.calls += 1
            if log:
                run.entries.append((child, h + 1, run.found, dropping))
            if audit:
                _audit(state, run, path)
            if watch is not None:
                watch.entered(state, path)
            continue
        found = best[-1]
        state.depth = h
        if watch is not None:
            watch.closing(state, path, found)
        if found <= k:
            state.fruitful(v, found)
            period_end = looked + state.extra + state.cost + written
            up = found + 1
        else:
            state.fruitless(v, h)
            up = k + 2
        if watch is not None:
            watch.repaired(state, path, found)
        on[v] = 0
        path.pop(), cursor.pop(), best.pop()
        if watch is not None:
            watch.closed(state, path, v, found)
        if path and up < best[-1]:
            best[-1] = up
        if audit and path:
            _audit(state, run, path)
    tell("end")
    if not run.capped and outputs:
        run.phases.append(looked + state.extra + state.cost + written)
    run.steps = {"search": looked + state.extra, "cascade": state.cost, "output": written, "bfs": 0, "seed": seeding}


def _total(event: tuple) -> int:
    return sum(event[1:])


def _audit(state: _Barriers, run: Run, path: list[int]) -> None:
    """Counts, at a moment without repair under way, edges and nodes whose barriers break an invariant."""
    b, on, csr, t, k = state.b, state.on, state.csr, state.t, state.k
    bad = run.violations
    for name in ("consistency", "admissible", "range", "guard"):
        bad.setdefault(name, 0)
    for x in range(csr.n):
        if not on[x] and x != t:
            for y in csr.succ[x]:
                if (not on[y] or y == t) and b[x] > (0 if y == t else b[y]) + 1:
                    bad["consistency"] += 1
        if not 0 <= b[x] <= k + 1:
            bad["range"] += 1
    skip = list(on)
    true, _ = distances_to(csr, t, k, skip)
    for x in range(csr.n):
        if not on[x] and b[x] > true[x]:
            bad["admissible"] += 1
    if len(path) > 1 and b[path[-1]] > k - (len(path) - 1):
        bad["guard"] += 1


def _fresh(csr: Csr, s: int, t: int, k: int, mutate: bool, cap: int | None) -> Run:
    """Every frame prunes by exact distances that avoid the path, from a search of its own; mutate takes path nodes out of the graph."""
    run = Run()
    k = min(k, csr.n)
    run.steps = dict.fromkeys(("search", "cascade", "output", "bfs", "seed"), 0)
    if k <= 0:
        return run
    on = bytearray(csr.n)
    graph = Csr(csr.names, csr.succ, [list(p) for p in csr.pred]) if mutate else csr
    taken: list[list[tuple[int, int]]] = []
    st = run.steps

    def tell(kind: str) -> None:
        run.events.append((kind, st["search"], 0, st["output"], st["bfs"]))

    def enter(v: int) -> list[int]:
        on[v] = 1
        st["search"] += 1
        run.calls += 1
        if mutate:
            out = []
            for w in csr.succ[v]:
                at = graph.pred[w].index(v)
                del graph.pred[w][at]
                out.append((w, at))
            taken.append(out)
        d, steps = distances_to(graph, t, k - len(path), () if mutate else on)
        st["bfs"] += steps
        return d

    path: list[int] = []
    frames = [(enter(s), iter(csr.succ[s]))]
    path.append(s)
    tell("start")
    while path:
        d, rest = frames[-1]
        h = len(path) - 1
        child = -1
        for w in rest:
            st["search"] += 1
            if h + d[w] >= k:
                continue
            if w == t:
                st["output"] += h + 2
                run.outputs.append((*path, t))
                tell("output")
                if cap is not None and len(run.outputs) >= cap:
                    run.capped = True
                    tell("end")
                    return run
            elif not on[w]:
                child = w
                break
        if child >= 0:
            frames.append((enter(child), iter(csr.succ[child])))
            path.append(child)
            continue
        v = path.pop()
        frames.pop()
        on[v] = 0
        if mutate:
            for w, at in reversed(taken.pop()):
                graph.pred[w].insert(at, v)
    tell("end")
    return run


def _unbounded(csr: Csr, s: int, t: int, scheme: str, cap: int | None) -> Run:
    """All simple paths of any length: by blocking (`circuit`), or by plain backtracking."""
    run = Run()
    blocking = scheme == "circuit"
    on = bytearray(csr.n)
    blocked = bytearray(csr.n)
    behind: list[dict[int, None]] = [{} for _ in range(csr.n)]
    st = run.steps = dict.fromkeys(("search", "cascade", "output", "bfs", "seed"), 0)

    def free(v: int) -> None:
        todo = [v]
        while todo:
            x = todo.pop()
            if blocked[x]:
                blocked[x] = 0
                st["cascade"] += 1 + len(behind[x])
                todo += behind[x]
                behind[x] = {}

    path, frames, hit = [s], [iter(csr.succ[s])], [False]
    on[s] = blocked[s] = 1
    st["search"], run.calls = 1, 1
    while path:
        v = path[-1]
        child = -1
        for w in frames[-1]:
            st["search"] += 1
            if w == t:
                run.outputs.append((*path, t))
                st["output"] += len(path) + 1
                hit[-1] = True
                if cap is not None and len(run.outputs) >= cap:
                    run.capped = True
                    return run
            elif not on[w] and not (blocking and blocked[w]):
                child = w
                break
        if child >= 0:
            path.append(child)
            frames.append(iter(csr.succ[child]))
            hit.append(False)
            on[child] = blocked[child] = 1
            st["search"] += 1
            run.calls += 1
            continue
        path.pop(), frames.pop()
        on[v] = 0
        if hit.pop():
            free(v)
            if hit:
                hit[-1] = True
        elif blocking:
            for w in csr.succ[v]:
                behind[w][v] = None
    return run


def weighted_paths(csr: Csr, weight: Callable[[int, int], int], s: int, t: int, budget: int) -> list[tuple[int, ...]]:
    """Simple s-t paths of total weight at most budget, pruned by exact fixed distances to t. Weights are non-negative integers."""
    import heapq

    far = budget + 1
    d = [far] * csr.n
    d[t] = 0
    todo = [(0, t)]
    while todo:
        x, v = heapq.heappop(todo)
        if x > d[v]:
            continue
        for p in csr.pred[v]:
            if (y := x + weight(p, v)) < d[p]:
                d[p] = y
                heapq.heappush(todo, (y, p))
    out, path, used, frames, on = [], [s], [0], [iter(csr.succ[s])], {s}
    while path:
        v = path[-1]
        for w in frames[-1]:
            cost = used[-1] + weight(v, w)
            if cost + d[w] > budget:
                continue
            if w == t:
                out.append((*path, t))
            elif w not in on:
                path.append(w), used.append(cost), frames.append(iter(csr.succ[w])), on.add(w)
                break
        else:
            on.discard(path.pop())
            used.pop(), frames.pop()
    return out
