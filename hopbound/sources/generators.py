"""Exact and pseudo-random graphs for experiments, as (edges (src, dst, ord), s, t)."""

from __future__ import annotations

from collections.abc import Iterator

Made = tuple[list[tuple[int, int, int]], int, int]


def lcg(seed: int) -> Iterator[int]:
    """Draws of the 31-bit linear congruential generator that SQL oracles use as well."""
    x = seed
    while True:
        x = (x * 1103515245 + 12345) % 2147483648
        yield x


def _listed(rows: dict[int, list[int]]) -> list[tuple[int, int, int]]:
    return [(a, b, i) for a, bs in rows.items() for i, b in enumerate(bs)]


# The two counter-example graphs, by successor lists.
FIG_X = {"A": "BC", "B": "CDE", "C": "BD", "D": "B"}
FIG_Y = {"A": "D", "B": "DEF", "D": "ABC", "E": "ABD", "F": "B"}


def lettered(lists: dict[str, str]) -> list[tuple[str, str, int]]:
    return [(a, b, i) for a, bs in lists.items() for i, b in enumerate(bs)]


def clique_trap(c: int, leave: bool = False) -> Made:
    """All edges among c nodes and a target c, isolated, or with leave behind an edge from 0 that is scanned first."""
    edges = [(a, b, b + 1) for a in range(c) for b in range(c) if a != b]
    return edges + [(0, c, 0)] * leave, 0, c


def hub_breaker(k: int) -> Made:
    """A long path to t with a detour chain into a hub of fans, on which coarse resets keep re-entering the hub; k divisible by 4, k >= 8."""
    if k % 4 or k < 8:
        raise ValueError("k must be a multiple of 4, at least 8")
    p = k // 2 - 1
    s, t, hub = 0, 1, 2
    v = [None, *range(3, 3 + p)]
    d = [None, *range(3 + p, 3 + 3 * p)]
    fan = list(range(3 + 3 * p, 3 + 3 * p + k))
    rows: dict[int, list[int]] = {s: [v[1], t], hub: [*fan, d[1]]}
    for i in range(1, p + 1):
        rows[v[i]] = [v[i + 1] if i < p else t, d[1]]
    for j in range(1, 2 * p + 1):
        back = [v[j - p]] if j - p >= 2 and j < 2 * p else []
        rows[d[j]] = [d[j + 1], hub, *back] if j < 2 * p else [hub, v[p]]
    return _listed(rows), s, t


def factorial_trap(k: int) -> Made:
    """s leads to every node of a clique of k - 1 nodes first, then along a path of two edges to t."""
    clique = list(range(1, k))
    rows = {0: [*clique, k]} | {a: [b for b in clique if b != a] for a in clique} | {k: [k + 1]}
    return _listed(rows), 0, k + 1


def uniform_digraph(seed: int, n: int | None = None, m: int | None = None) -> Made:
    """m different ordered pairs of n nodes; n from 6 to 30 and m / n log-uniform over 1 to n - 1 unless given."""
    draw = lcg(seed * 7919 + 17)
    for _ in range(5):
        next(draw)
    n = n or 6 + next(draw) // 65536 % 25
    if m is None:
        u = next(draw) / 2147483648
        m = max(1, min(n * (n - 1), round(n * (n - 1) ** u)))
    pairs = [(a, b) for a in range(n) for b in range(n) if a != b]
    for i in range(m):  # partial shuffle
        j = i + (next(draw) // 256) % (len(pairs) - i)
        pairs[i], pairs[j] = pairs[j], pairs[i]
    s = next(draw) // 65536 % n
    t = (s + 1 + next(draw) // 65536 % (n - 1)) % n
    return [(a, b, b) for a, b in pairs[:m]], s, t


def small_world(seed: int, n: int = 1000, degree: int = 6, rewire: float = 0.2) -> Made:
    """A ring lattice with rewired ends, made symmetric: n * degree directed edges."""
    draw = lcg(seed * 104729 + 71)
    for _ in range(5):
        next(draw)
    near: list[set[int]] = [set() for _ in range(n)]

    def join(a: int, b: int) -> None:
        near[a].add(b)
        near[b].add(a)

    for a in range(n):
        for o in range(1, degree // 2 + 1):
            join(a, (a + o) % n)
    for o in range(1, degree // 2 + 1):
        for a in range(n):
            b = (a + o) % n
            if next(draw) / 2147483648 < rewire and b in near[a]:
                c = next(draw) // 1024 % n
                while c == a or c in near[a]:
                    c = next(draw) // 1024 % n
                near[a].discard(b)
                near[b].discard(a)
                join(a, c)
    s = next(draw) // 1024 % n
    t = (s + 1 + next(draw) // 1024 % (n - 1)) % n
    return [(a, b, b) for a in range(n) for b in sorted(near[a])], s, t


FAMILIES = {"clique_trap": clique_trap, "hub_breaker": hub_breaker, "factorial_trap": factorial_trap, "uniform_digraph": uniform_digraph, "small_world": small_world}
