"""Conjunctive queries whose answers are the instances of a pattern, each once.

A query has one oriented edge subgoal for each edge of the pattern and conditions on the order of its variables.
Three ways lead from a pattern to a set of queries: one for each class of node orders under the pattern's symmetry,
those merged where they orient the edges alike, and one for each class of acyclic orientations. Cycles have a
fourth: one for each class of run lengths of ups and downs around the cycle.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Callable, Iterable
from dataclasses import dataclass

from motifscan.plans.patterns import Pattern, automorphisms, break_symmetry, cycle

Pair = tuple[int, int]


@dataclass(frozen=True)
class MotifQuery:
    """subgoals (a, b): an edge with x_a < x_b. less: further pairs x_i < x_j. differ: x_i != x_j. orders: if there, one of these node orders holds too."""

    p: int
    subgoals: tuple[Pair, ...]
    less: tuple[Pair, ...] = ()
    differ: tuple[Pair, ...] = ()
    orders: tuple[tuple[int, ...], ...] = ()

    def accepts(self, value: tuple[int, ...] | list[int]) -> bool:
        """Whether an assignment meets the conditions (edges aside)."""
        return all(value[a] < value[b] for a, b in (*self.subgoals, *self.less)) and all(value[a] != value[b] for a, b in self.differ) and (not self.orders or any(all(value[o[i]] < value[o[i + 1]] for i in range(self.p - 1)) for o in self.orders))

    def condition_sql(self, names: list[str]) -> str:
        """The conditions as SQL text."""
        parts = [f"{names[a]} < {names[b]}" for a, b in dict.fromkeys((*self.subgoals, *self.less))] + [f"{names[a]} <> {names[b]}" for a, b in self.differ]
        if self.orders:
            parts.append("(" + " OR ".join("(" + " AND ".join(f"{names[o[i]]} < {names[o[i + 1]]}" for i in range(self.p - 1)) + ")" for o in self.orders) + ")")
        return " AND ".join(parts) or "TRUE"

    def to_sql(self, edge_view: str) -> str:
        """A statement over a view (src, dst) with src < dst."""
        names = [f"x{i}" for i in range(self.p)]
        at: dict[int, str] = {}
        joins, where = [], []
        for n, (a, b) in enumerate(self.subgoals):
            joins.append(f"{edge_view} e{n}")
            for v, c in ((a, f"e{n}.src"), (b, f"e{n}.dst")):
                if v in at:
                    where.append(f"{at[v]} = {c}")
                else:
                    at[v] = c
        inner = f"SELECT {', '.join(f'{at[v]} AS x{v}' for v in sorted(at))} FROM {', '.join(joins)}" + (f" WHERE {' AND '.join(where)}" if where else "")
        return f"SELECT * FROM ({inner}) t WHERE {self.condition_sql(names)}"


def _closure(p: int, pairs: Iterable[Pair]) -> list[list[bool]]:
    under = [[False] * p for _ in range(p)]
    for a, b in pairs:
        under[a][b] = True
    for k, i, j in itertools.product(range(p), repeat=3):
        under[i][j] = under[i][j] or under[i][k] and under[k][j]
    return under


def _acyclic(p: int, pairs: Iterable[Pair]) -> bool:
    under = _closure(p, pairs)
    return not any(under[i][i] for i in range(p))


def _finished(p: int, subgoals: tuple[Pair, ...], less: Iterable[Pair], orders: tuple[tuple[int, ...], ...] = ()) -> MotifQuery:
    """With `!=` for every pair that the other conditions leave open."""
    less = tuple(sorted(set(less) - set(subgoals)))
    under = _closure(p, (*subgoals, *less))
    differ = tuple((i, j) for i in range(p) for j in range(i + 1, p) if not under[i][j] and not under[j][i])
    return MotifQuery(p, subgoals, less, differ, orders)


def oriented(s: Pattern, rank: list[int] | tuple[int, ...]) -> tuple[Pair, ...]:
    return tuple((a, b) if rank[a] < rank[b] else (b, a) for a, b in s.edges)


def cq_from_order(s: Pattern, order: tuple[int, ...]) -> MotifQuery:
    """The query of one total order: order[0] is the least variable."""
    rank = [0] * s.p
    for i, v in enumerate(order):
        rank[v] = i
    return MotifQuery(s.p, oriented(s, rank), tuple((order[i], order[i + 1]) for i in range(s.p - 1)))


def order_classes(s: Pattern, pick: str | tuple[Pair, ...] = "lex") -> list[tuple[int, ...]]:
    """One order of each class under the pattern's symmetry: the lexicographically least, or the one that meets the inequalities (a, b): a before b."""
    group, left, out = automorphisms(s), set(itertools.permutations(range(s.p))), []
    for order in itertools.permutations(range(s.p)):
        if order not in left:
            continue
        images = {tuple(g[v] for v in order) for g in group}
        left -= images
        if pick == "lex":
            out.append(order)
            continue
        fit = [o for o in images if all(o.index(a) < o.index(b) for a, b in pick)]
        if len(fit) != 1:
            raise ValueError(f"{len(fit)} orders of a class meet the inequalities; it must be 1")
        out.append(fit[0])
    return out


def cqs_by_orders(s: Pattern, pick: str | tuple[Pair, ...] = "lex") -> list[MotifQuery]:
    return [cq_from_order(s, o) for o in order_classes(s, pick)]


def _extensions(p: int, under: list[list[bool]]) -> int:
    """How many total orders extend a partial one."""
    ways = {0: 1}
    for done in range(1 << p):
        if n := ways.get(done):
            for v in range(p):
                if not done >> v & 1 and all(done >> u & 1 for u in range(p) if under[u][v]):
                    ways[done | 1 << v] = ways.get(done | 1 << v, 0) + n
    return ways.get((1 << p) - 1, 0)


def simplify(s: Pattern, orders: list[tuple[int, ...]]) -> MotifQuery:
    """One query for orders of the same orientation: their common partial order if no other order extends it, else with the orders left as alternatives."""
    at = [{v: i for i, v in enumerate(o)} for o in orders]
    common = [(i, j) for i, j in itertools.permutations(range(s.p), 2) if all(a[i] < a[j] for a in at)]
    under = _closure(s.p, common)
    subgoals = oriented(s, [at[0][v] for v in range(s.p)])
    least = [(i, j) for i, j in common if not any(under[i][k] and under[k][j] for k in range(s.p))]
    return _finished(s.p, subgoals, least, () if _extensions(s.p, under) == len(orders) else tuple(orders))


def merge_by_orientation(s: Pattern, orders: list[tuple[int, ...]] | None = None) -> list[MotifQuery]:
    """The queries of the order classes, merged where they orient all edges alike."""
    groups: dict[tuple[Pair, ...], list[tuple[int, ...]]] = {}
    for o in orders or order_classes(s):
        groups.setdefault(cq_from_order(s, o).subgoals, []).append(o)
    return [simplify(s, g) for g in groups.values()]


def acyclic_orientations(s: Pattern) -> list[tuple[Pair, ...]]:
    out = []
    for flips in itertools.product((False, True), repeat=len(s.edges)):
        o = tuple((b, a) if f else (a, b) for f, (a, b) in zip(flips, s.edges, strict=True))
        if _acyclic(s.p, o):
            out.append(o)
    return out


def moved(s: Pattern, o: tuple[Pair, ...], g: tuple[int, ...]) -> tuple[Pair, ...]:
    """An orientation's image under a symmetry."""
    up = {(g[a], g[b]) for a, b in o}
    return tuple((a, b) if (a, b) in up else (b, a) for a, b in s.edges)


def bidirectional(queries: list[MotifQuery]) -> int:
    """How many edges are used in both directions by the queries together: these are shipped twice where all are evaluated together."""
    return sum((b, a) in {e for q in queries for e in q.subgoals} for a, b in {e for q in queries for e in q.subgoals}) // 2


def orientation_query(s: Pattern, o: tuple[Pair, ...]) -> MotifQuery:
    fixing = tuple(g for g in automorphisms(s) if moved(s, o, g) == o)
    return _finished(s.p, o, break_symmetry(fixing))


def cqs_by_orientation(s: Pattern, minimise: str | None = None) -> list[MotifQuery]:
    """One query for each class of acyclic orientations; those that keep an orientation are told apart by inequalities. minimise='bidirectional' picks, class by class, the image that adds fewest edges in both directions."""
    group, left, picked = automorphisms(s), dict.fromkeys(acyclic_orientations(s)), []
    used: set[Pair] = set()
    while left:
        first = next(iter(left))
        images = sorted({moved(s, first, g) for g in group})
        for i in images:
            left.pop(i, None)
        best = min(images, key=lambda o: sum((b, a) in used for a, b in o)) if minimise == "bidirectional" else first
        used |= set(best)
        picked.append(best)
    return [orientation_query(s, o) for o in picked]


# cycles


def even_bags(p: int) -> list[tuple[int, ...]]:
    """Multisets of positive integers, even in number, that sum to p."""
    out: list[tuple[int, ...]] = []

    def grow(rest: int, least: int, bag: tuple[int, ...]) -> None:
        if not rest and len(bag) % 2 == 0:
            out.append(bag)
        for n in range(least, rest + 1):
            grow(rest - n, n, (*bag, n))

    grow(p, 1, ())
    return out


def flip(updown: str) -> str:
    """The same cycle walked the other way: reversed, with ups and downs exchanged."""
    return updown[::-1].translate(str.maketrans("ud", "du"))


def updown(runs: tuple[int, ...]) -> str:
    return "".join("ud"[i % 2] * n for i, n in enumerate(runs))


def run_classes(p: int) -> list[tuple[int, ...]]:
    """One run sequence (lengths of ups, downs, ups, ...) of each class under shifts by an even number of runs and reversal."""
    seen: set[tuple[int, ...]] = set()
    out = []
    for bag in even_bags(p):
        for runs in sorted(set(itertools.permutations(bag))):
            if runs in seen:
                continue
            turns = [runs[i:] + runs[:i] for i in range(0, len(runs), 2)]
            seen |= {*turns, *(t[::-1] for t in turns)}
            out.append(runs)
    return out


def characteristic_sequence(nodes: list[int] | tuple[int, ...]) -> tuple[int, ...]:
    """The run lengths of a concrete cycle, from its least node on, in the direction whose sequence is least."""
    at = nodes.index(min(nodes))
    out = []
    for turn in (nodes[at:] + nodes[:at], (nodes[at:] + nodes[:at])[:1] + (nodes[at:] + nodes[:at])[:0:-1]):
        ups = ["u" if turn[i] < turn[(i + 1) % len(turn)] else "d" for i in range(len(turn))]
        out.append(tuple(len(list(g)) for _, g in itertools.groupby(ups)))
    return min(out)


def _cycle_orientation(p: int, ups: str) -> tuple[Pair, ...]:
    return tuple((i, (i + 1) % p) if u == "u" else ((i + 1) % p, i) for i, u in enumerate(ups))


def cycle_cqs(p: int, strict_text: bool = False) -> list[MotifQuery]:
    """One query for each class of run sequences, with the inequalities that tell its own symmetries apart.

    strict_text takes the remedies literally: the first run starts at the least of all local minima of a periodic
    sequence, the second node below the last of a palindromic one, and nothing for what is both only after a shift;
    nodes that aren't neighbours aren't compared. It finds some cycles twice and misses others.
    """
    s, out = cycle(p), []
    if not strict_text:
        for runs in run_classes(p):
            o = _cycle_orientation(p, updown(runs))
            out.append(orientation_query(s, tuple((a, b) if (a, b) in o else (b, a) for a, b in s.edges)))
        return out
    for runs in run_classes(p):
        o, less = _cycle_orientation(p, updown(runs)), []
        half = len(runs) // 2
        starts = [sum(runs[:i]) for i in range(0, len(runs), 2)]
        if any(half % d == 0 and runs == runs[: 2 * d] * (half // d) for d in range(1, half)):
            less += [(0, m) for m in starts[1:]]
        if runs == runs[::-1]:
            less.append((1, p - 1))
        out.append(MotifQuery(p, o, tuple(less)))
    return out


def cycle_cq_bound(p: int) -> float:
    """The estimate (2^p - 2) / 2p: exact for prime p, below the count otherwise."""
    return (2**p - 2) / (2 * p)


def cycle_cq_count(p: int) -> int:
    """How many classes there are, by counting orbits of up-down strings under rotation and flip."""
    fixed = sum(2 ** math.gcd(p, i) - 2 for i in range(p))
    return (fixed + (p // 2 * 2 ** (p // 2) if p % 2 == 0 else 0)) // (2 * p)


def found_once(s: Pattern, queries: list[MotifQuery], rank: tuple[int, ...] | list[int]) -> int:
    """How often the queries together find the instance whose nodes have these ranks: over all its images."""
    return sum(q.accepts([rank[g[v]] for v in range(s.p)]) for g in automorphisms(s) for q in queries)


Compile = Callable[[list[str]], str]
