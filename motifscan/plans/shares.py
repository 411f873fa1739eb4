"""Shares: how many buckets each variable's values are hashed to, so that k keys cost the fewest shipped pairs."""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np

from motifscan.plans.cqs import MotifQuery
from motifscan.plans.patterns import Pattern


@dataclass(frozen=True)
class Term:
    """A relation of `size` rows whose rows fix the buckets of two variables and go to every bucket of the others."""

    a: int
    b: int
    size: float = 1.0


def terms(s: Pattern, queries: Iterable[MotifQuery]) -> tuple[Term, ...]:
    """A term for each edge of the pattern; an edge that the queries use in both directions is shipped twice."""
    used = {e for q in queries for e in q.subgoals}
    return tuple(Term(a, b, float(((a, b) in used) + ((b, a) in used))) for a, b in s.edges)


def cost(p: int, ts: Iterable[Term], shares: dict[int, float] | list[float]) -> float:
    """Pairs per edge: each term's size times the shares of the variables it lacks."""
    return sum(t.size * math.prod(shares[v] for v in range(p) if v not in (t.a, t.b)) for t in ts)


def sums(p: int, ts: Iterable[Term], shares: dict[int, float] | list[float]) -> list[float]:
    """For each variable, the cost of the terms that lack it. At the optimum they are equal wherever the share is over 1."""
    each = [(t, t.size * math.prod(shares[v] for v in range(p) if v not in (t.a, t.b))) for t in ts]
    return [sum(c for t, c in each if v not in (t.a, t.b)) for v in range(p)]


def dominated(p: int, ts: tuple[Term, ...]) -> set[int]:
    """Variables that stand only in terms where one other variable stands too: they need no buckets of their own."""
    of = {v: {i for i, t in enumerate(ts) if v in (t.a, t.b)} for v in range(p)}
    out: set[int] = set()
    for v in range(p):
        if any(w != v and w not in out and of[v] <= of[w] and (of[v] < of[w] or w < v) for w in range(p)):
            out.add(v)
    return out


def optimise(p: int, ts: tuple[Term, ...], k: float, drop_dominated: bool = False) -> list[float]:
    """Real shares of at least 1 with product k and least cost: Newton's method on the logarithms, with an active set of shares held at 1."""
    if k <= 1:
        return [1.0] * p
    absent = np.array([[v not in (t.a, t.b) for v in range(p)] for t in ts], float)
    size = np.log(np.array([t.size for t in ts]))
    held = dominated(p, ts) if drop_dominated else set()
    for _ in range(4 * p):
        free = [v for v in range(p) if v not in held]
        y = np.zeros(p)
        y[free] = math.log(k) / len(free)
        for _ in range(200):
            w = np.exp(size + absent @ y)
            w /= w.max()
            g = absent.T @ w
            h = (absent.T * w) @ absent + 1e-12 * np.eye(p)
            n = len(free)
            system = np.zeros((n + 1, n + 1))
            system[:n, :n], system[:n, n], system[n, :n] = h[np.ix_(free, free)], 1, 1
            step = np.linalg.lstsq(system, np.append(-g[free], 0), rcond=None)[0][:n]
            f0, t = np.log(np.exp(size + absent @ y).sum()), 1.0
            while t > 1e-9:
                z = y.copy()
                z[free] += t * step
                if np.log(np.exp(size + absent @ z).sum()) <= f0 + 1e-15:
                    break
                t /= 2
            moved = np.abs(z - y).max()
            y = z
            if moved < 1e-13:
                break
        low = [v for v in free if y[v] < -1e-9]
        if low:
            held.add(min(low, key=lambda v: y[v]))
            continue
        g = absent.T @ np.exp(size + absent @ y)
        common = g[free].mean() if free else 0
        back = [v for v in held if g[v] < common * (1 - 1e-9) and not drop_dominated]  # a larger share would cost less
        if not back:
            break
        held.discard(min(back, key=lambda v: g[v]))
    return [float(math.exp(max(0.0, v))) for v in y]


def round_shares(p: int, ts: tuple[Term, ...], real: list[float], k: float) -> list[int]:
    """Whole shares near the real ones whose product is at most k, with the largest product and then the least cost a key."""
    best: tuple | None = None
    for c in itertools.product(*(sorted({max(1, math.floor(r)), max(1, math.ceil(r - 1e-9)), max(1, round(r))}) for r in real)):
        n = math.prod(c)
        if n <= k * (1 + 1e-9) or n == 1:
            rank = (cost(p, ts, list(c)) / n ** (1 - 2 / p) if p > 2 else 0, -n, c)
            best = min(best, rank) if best else rank
    return list(best[2]) if best else [1] * p


def regular_shares(s: Pattern, k: float) -> list[float]:
    """One query of a regular pattern: all shares are equal."""
    if s.regular() is None:
        raise ValueError("the pattern isn't regular")
    return [k ** (1 / s.p)] * s.p


def _split(s: Pattern, both: set[tuple[int, int]]) -> tuple[set[int], set[int]] | None:
    """Nodes whose edges all go one way, and the others, if the two-class conditions hold: a node's edges are all of one kind to its own side."""
    one = {v for v in range(s.p) if not any(v in e for e in both)}
    return one, set(range(s.p)) - one


def two_class_shares(s: Pattern, both: set[tuple[int, int]], k: float) -> list[float] | None:
    """A regular pattern all of whose terms can be made equal by two values of shares, one twice the other. `both`: edges used in both directions.

    Terms are equal if the product of the two shares is in proportion to the coefficient. None if no such classes exist.
    """
    if s.regular() is None:
        return None
    ratio: dict[int, int] = {}
    need = {e: 1 if e in both else 0 for e in s.edges}
    for start in (0, 1):  # exponents of 2 with sum 1 over a doubled edge, 0 over others, up to a common offset
        for offset in (0, -1, 1):
            ratio = {0: start}
            todo, ok = [0], True
            while todo and ok:
                v = todo.pop()
                for w in s.neighbours(v):
                    r = need[tuple(sorted((v, w)))] + 1 + offset - ratio[v]
                    if w not in ratio:
                        ratio[w] = r
                        todo.append(w)
                    ok = ok and ratio[w] == r
            values = set(ratio.values())
            if ok and len(ratio) == s.p and max(values) - min(values) <= 1:
                low = min(values)
                base = (k / math.prod(2.0 ** (ratio[v] - low) for v in range(s.p))) ** (1 / s.p)
                return [base * 2.0 ** (ratio[v] - low) for v in range(s.p)]
    return None


def cycle_shares(p: int, k: float) -> list[float]:
    """All queries of a cycle together, its least node first: edges at node 0 go one way, the others both, and node 0 has half the common share."""
    common = (2 * k) ** (1 / p)
    return [common / 2] + [common] * (p - 1)


@dataclass(frozen=True)
class ThreeClasses:
    """Nodes with only two-way edges (s1), with edges of both kinds (s2), and with only one-way edges (s3)."""

    s1: frozenset[int]
    s2: frozenset[int]
    s3: frozenset[int]


def three_classes(s: Pattern, both: set[tuple[int, int]]) -> ThreeClasses:
    kinds = {v: {e in both for e in s.edges if v in e} for v in range(s.p)}
    return ThreeClasses(*(frozenset(v for v in range(s.p) if kinds[v] == k) for k in ({True}, {True, False}, {False})))


def three_class_shares(s: Pattern, both: set[tuple[int, int]], k: float, option: str | None = None) -> list[float] | None:
    """Shares with one value for each class (a for s1, z for s2, b for s3), product k, and equal sums over all nodes; None if no such shares exist.

    option 'a=z' or 'b=z' takes two of the values equal. Solved numerically in the ratios and then checked, since the
    closed forms hold for special neighbour counts only.
    """
    ts = tuple(Term(a, b, 2.0 if (a, b) in both else 1.0) for a, b in s.edges)
    c = three_classes(s, both)
    groups = [g for g in (c.s1, c.s2, c.s3)]
    if option == "a=z":
        groups = [c.s1 | c.s2, c.s3]
    elif option == "b=z":
        groups = [c.s1, c.s2 | c.s3]
    elif option == "a=b=z":
        groups = [c.s1 | c.s2 | c.s3]
    groups = [sorted(g) for g in groups if g]
    q = len(groups)
    merged = np.array([[sum(v not in (t.a, t.b) for v in g) for g in groups] for t in ts], float)
    weight, size = np.array([len(g) for g in groups], float), np.log([t.size for t in ts])
    y = np.full(q, math.log(k) / s.p)
    for _ in range(300):
        w = np.exp(size + merged @ y)
        w /= w.max()
        g, h = merged.T @ w, (merged.T * w) @ merged
        system = np.zeros((q + 1, q + 1))
        system[:q, :q], system[:q, q], system[q, :q] = h, weight, weight
        step = np.linalg.lstsq(system, np.append(-g, 0), rcond=None)[0][:q]
        y = y + np.clip(step, -1, 1)
        if np.abs(step).max() < 1e-14:
            break
    shares = [0.0] * s.p
    for v, g in zip(y, groups, strict=True):
        for node in g:
            shares[node] = float(math.exp(v))
    totals = sums(s.p, ts, shares)
    return shares if max(totals) - min(totals) <= 1e-6 * max(totals) and min(shares) > 0 else None


def class_consistency(s: Pattern, both: set[tuple[int, int]]) -> bool:
    """Whether shares by classes make all sums equal at all."""
    return any(three_class_shares(s, both, 1024.0, option) is not None for option in (None, "a=z", "b=z"))


def replication_equal_thirds(p: int, d: float, k: float) -> float:
    """Pairs per edge of a pattern of degree d with three classes of a third of the nodes each, half of whose neighbours are of their own kind. Shares: k^(1/p) for s2, and 2^(1/3) times more for s1 and less for s3."""
    return k ** (1 - 2 / p) * p * d * (2 ** (1 / 3) + 2 ** (2 / 3)) / 4


def replication_covering(p: int, d: float, k: float, s3: int) -> float:
    """Pairs per edge if the nodes with edges of both kinds are independent and cover all edges; s3: how many nodes have one-way edges only."""
    return k * p * d / (2 ** (2 * s3 / p) * k ** (2 / p))
