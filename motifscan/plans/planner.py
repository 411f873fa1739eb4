"""Chooses a scheme and its parameters for a budget of keys, from a graph's size and degrees."""

from __future__ import annotations

import math
from dataclasses import dataclass

from motifscan.plans import costs
from motifscan.plans import shares as sh
from motifscan.plans.cqs import MotifQuery, acyclic_orientations, cqs_by_orientation, moved, orientation_query
from motifscan.plans.patterns import Pattern, automorphisms


@dataclass(frozen=True)
class Scheme:
    """name: bucket, variable, degree or bounded (the last two without keys: joins along degree order, or along neighbours). pairs: expected rows shipped for each edge. note: what speaks against the scheme, if anything."""

    name: str
    b: int = 0
    shares: tuple[int, ...] = ()
    pairs: float = 0.0
    note: str = ""


def buckets_for_memory(m: int, p: int, edges: float) -> int:
    """The least b whose keys hold `edges` edges on average at most: about m p (p - 1) / b^2."""
    return max(1, math.ceil(math.sqrt(m * p * (p - 1) / edges)))


def buckets_for(k: int, p: int) -> int:
    return max((b for b in range(1, 4096) if math.comb(b + p - 1, p) <= k), default=1)


def plan(s: Pattern, k: int | None = None, m: int | None = None, two_paths: int | None = None, max_degree: int | None = None, edges_per_key: float | None = None, n: int | None = None) -> Scheme:
    """The scheme that ships least, for a number of keys k, or for so many edges of a key at most (with m). Neither of the two key schemes wins in general.

    Joining along degree order ships two_paths + 2 m rows for triangles whatever k is; growing any connected pattern
    along neighbours ships the rows of its partial matches, m * max_degree^i at most.
    """
    if k is None:
        if m is None or edges_per_key is None:
            raise ValueError("a number of keys, or m and edges_per_key")
        k = math.comb(buckets_for_memory(m, s.p, edges_per_key) + s.p - 1, s.p)
    b = buckets_for(k, s.p)
    # growing along neighbours does no more work at all keys together than alone only while a key keeps the degree bound
    thin = bool(n and max_degree) and not costs.degree_ok(max_degree, b, n)
    found = [Scheme("bucket", b=b, pairs=float(costs.bucket_pairs(b, s.p)), note=f"{b} buckets leave less than log n of a degree of {max_degree}: the keys together may do more work than one machine" if thin else "")]
    queries = cheapest_queries(s, k)
    ts = sh.terms(s, queries)
    whole = sh.round_shares(s.p, ts, sh.optimise(s.p, ts, k), k)
    found.append(Scheme("variable", shares=tuple(whole), pairs=sh.cost(s.p, ts, list(whole))))
    if s.p == 3 and len(s.edges) == 3 and m and two_paths is not None:
        found.append(Scheme("degree", pairs=two_paths / m + 2))
    elif s.connected() and max_degree:
        # each join ships what is matched so far, and the edges both ways
        found.append(Scheme("bounded", pairs=sum(2.0 * max_degree**i + 2 for i in range(s.p - 2))))
    return min(found, key=lambda x: x.pairs)


def cheapest_queries(s: Pattern, k: float, most: int = 100_000) -> list[MotifQuery]:
    """One query for each class of orientations, by those images that together use fewest edges in both directions, and of these ship least at k keys. Beyond `most` different choices, the images are picked class by class."""
    group, classes, seen = automorphisms(s), [], set()
    for o in acyclic_orientations(s):
        if o not in seen:
            images = sorted({moved(s, o, g) for g in group})
            seen.update(images)
            classes.append(images)
    # choices that use the same directions cost the same
    choices: dict[frozenset, tuple] = {frozenset(): ()}
    for images in classes:
        grown: dict[frozenset, tuple] = {}
        for used, picked in choices.items():
            for o in images:
                grown.setdefault(used | set(o), (*picked, o))
        if len(grown) > most:
            return cqs_by_orientation(s, "bidirectional")
        choices = grown
    both = lambda used: sum((b, a) in used for a, b in s.edges if (a, b) in used)
    least = min(map(both, choices))

    def shipped(used: frozenset) -> float:
        ts = tuple(sh.Term(a, b, float(((a, b) in used) + ((b, a) in used))) for a, b in s.edges)
        return sh.cost(s.p, ts, sh.optimise(s.p, ts, k))

    # different sets of such edges, by what they ship
    kinds = {frozenset(e for e in s.edges if e in used and e[::-1] in used): used for used in choices if both(used) == least}
    best = min(kinds.values(), key=lambda used: (round(shipped(used), 6), sorted(used)))
    return [orientation_query(s, o) for o in choices[best]]


def compare_grouping(s: Pattern, k: float, queries: list[MotifQuery] | None = None) -> dict[str, float]:
    """Pairs per edge of all queries together, and of a job for each: together is never more."""
    queries = queries or cqs_by_orientation(s)
    best = lambda qs: sh.cost(s.p, sh.terms(s, qs), sh.optimise(s.p, sh.terms(s, qs), k))
    return {"joint": best(queries), "separate": sum(best([q]) for q in queries), "best_single": min(best([q]) for q in queries)}
