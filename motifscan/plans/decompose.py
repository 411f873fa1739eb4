"""Splitting a pattern into parts whose instances can be found in optimal serial time, and orders in which to grow one."""

from __future__ import annotations

import itertools
from dataclasses import dataclass
from functools import lru_cache

from motifscan.plans.patterns import Pattern


@dataclass(frozen=True)
class Parts:
    """Nodes without partner, edges, and odd parts, each in the order of a Hamilton cycle. alpha, beta: the exponents of n and m in the time."""

    isolated: tuple[int, ...]
    edges: tuple[tuple[int, int], ...]
    odd: tuple[tuple[int, ...], ...]

    @property
    def alpha(self) -> float:
        return float(len(self.isolated))

    @property
    def beta(self) -> float:
        return len(self.edges) + sum(len(o) for o in self.odd) / 2

    def all(self) -> list[tuple[int, ...]]:
        return [*self.odd, *self.edges, *((v,) for v in self.isolated)]


def hamilton_cycle(s: Pattern, nodes: tuple[int, ...]) -> tuple[int, ...] | None:
    """A cycle through all of the nodes, from the first one on."""

    def grow(walk: list[int]) -> tuple[int, ...] | None:
        if len(walk) == len(nodes):
            return tuple(walk) if walk[0] in s.neighbours(walk[-1]) else None
        for w in sorted(s.neighbours(walk[-1]) & set(nodes) - set(walk)):
            if found := grow([*walk, w]):
                return found
        return None

    return grow([nodes[0]]) if len(nodes) >= 3 else None


def decompose(s: Pattern) -> Parts:
    """The split with the fewest nodes without partner; of those, with the fewest parts."""

    @lru_cache(maxsize=None)
    def best(left: frozenset[int]) -> tuple[int, int, tuple]:
        if not left:
            return 0, 0, ()
        v, rest = min(left), sorted(left - {min(left)})
        q, n, parts = best(left - {v})
        found = [(q + 1, n + 1, ((v,), *parts))]
        for w in rest:
            if w in s.neighbours(v):
                q, n, parts = best(left - {v, w})
                found.append((q, n + 1, ((v, w), *parts)))
        for size in range(2, len(rest) + 1, 2):
            for others in itertools.combinations(rest, size):
                if walk := hamilton_cycle(s, (v, *others)):
                    q, n, parts = best(left - {v, *others})
                    found.append((q, n + 1, (walk, *parts)))
        return min(found)

    parts = best(frozenset(range(s.p)))[2]
    return Parts(tuple(x[0] for x in parts if len(x) == 1), tuple(x for x in parts if len(x) == 2), tuple(x for x in parts if len(x) > 2))


def exponents(s: Pattern) -> tuple[float, float]:
    parts = decompose(s)
    return parts.alpha, parts.beta


def elimination_order(s: Pattern) -> tuple[int, ...]:
    """An order in which each node but the first has an earlier neighbour, that starts with an edge; connected patterns only."""
    if not s.connected() or s.p < 2:
        raise ValueError("the pattern must be connected and have an edge")
    degree = s.degrees()
    order = [max(range(s.p), key=lambda v: degree[v])]
    while len(order) < s.p:
        reach = [v for v in range(s.p) if v not in order and s.neighbours(v) & set(order)]
        order.append(max(reach, key=lambda v: (len(s.neighbours(v) & set(order)), degree[v], -v)))
    return tuple(order)
