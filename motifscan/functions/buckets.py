"""Column functions of the mapping schemes: buckets, numbers of bucket lists, ownership, canonical mappings."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

from motifscan.plans.patterns import Pattern, automorphisms, break_symmetry


#: Buckets of nodes where edges are made and packed, ids modulo a prime; coarser ones are these modulo a smaller number.
FINE = 61


def bucket_of(node: Column | str, b: int, kind: str = "xx", seed: int = 0) -> Column:
    """0..b-1; kind 'mod' takes the id itself modulo b, so that SQL elsewhere can follow."""
    node = F.col(node) if isinstance(node, str) else node
    return F.pmod(node if kind == "mod" else F.xxhash64(node, F.lit(seed)), F.lit(b)).cast("int")


def rank_multiset(buckets: Column, b: int, p: int) -> Column:
    """The dense number of a list of p buckets, whatever its order: 0 to C(b+p-1, p) - 1.

    In the sorted list, position i holds c_i; c_i + i strictly rises, and the number is the sum of C(c_i + i, i + 1).
    """
    ordered = F.sort_array(buckets)
    out = F.lit(0).cast("long")
    for i in range(p):
        table = F.array(*(F.lit(math.comb(c + i, i + 1)).cast("long") for c in range(b)))
        out = out + F.element_at(table, F.element_at(ordered, i + 1) + 1)
    return out


def rank_three(a: Column, b: Column, c: Column) -> Column:
    """rank_multiset of three buckets, by arithmetic alone."""
    low, high = F.least(a, b, c).cast("long"), F.greatest(a, b, c).cast("long")
    mid = a + b + c - low - high
    whole = lambda x, n: F.call_function("div", x, F.lit(n).cast("long"))
    return low + whole(mid * (mid + 1), 2) + whole(high * (high + 1) * (high + 2), 6)


def unrank_multiset(number: int, b: int, p: int) -> tuple[int, ...]:
    out = []
    for i in range(p - 1, -1, -1):
        c = max(c for c in range(b) if math.comb(c + i, i + 1) <= number)
        number -= math.comb(c + i, i + 1)
        out.append(c)
    return tuple(out[::-1])


def rank_python(buckets: Sequence[int]) -> int:
    return sum(math.comb(c + i, i + 1) for i, c in enumerate(sorted(buckets)))


def pack_tuple(buckets: Sequence[Column], shares: Sequence[int]) -> Column:
    """The number of a tuple of buckets in mixed radix."""
    out = F.lit(0).cast("long")
    for c, n in zip(buckets, shares, strict=True):
        out = out * n + c
    return out


def pairs_condition(pairs: Sequence[tuple[int, int]], names: Sequence[str]) -> Column:
    out = F.lit(True)
    for a, b in pairs:
        out = out & (F.col(names[a]) < F.col(names[b]))
    return out


def is_canonical(s: Pattern, names: Sequence[str]) -> Column:
    """Whether a mapping is the least of its images under the pattern's symmetry."""
    return pairs_condition(break_symmetry(automorphisms(s)), names)


def canonical_mapping(s: Pattern, names: Sequence[str]) -> list[Column]:
    """The least image of a mapping, as columns of the same names."""
    images = [F.struct(*(F.col(names[g[i]]).alias(f"c{i}") for i in range(s.p))) for g in automorphisms(s)]
    if len(images) == math.factorial(s.p):
        least = F.sort_array(F.array(*(F.col(n) for n in names)))
        return [F.element_at(least, i + 1).alias(names[i]) for i in range(s.p)]
    least = F.least(*images) if len(images) > 1 else images[0]
    return [least.getField(f"c{i}").alias(names[i]) for i in range(s.p)]


def up_downs(names: Sequence[str]) -> Column:
    """A cycle's string of u (up) and d (down) along its nodes, from the least one on: the characteristic sequence's runs. The direction is the one whose string is greater, so that reversals agree."""
    x = F.array(*(F.col(n) for n in names))
    n = len(names)
    at = F.array_position(x, F.array_min(x)).cast("int") - 1

    def along(step: int) -> Column:
        node = lambda i: F.get(x, F.pmod(at + F.lit(step) * i, F.lit(n)))
        return F.array_join(F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.when(node(i) < node(i + 1), "u").otherwise("d")), "")

    return F.greatest(along(1), along(-1))
