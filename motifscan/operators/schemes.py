"""Mapping schemes: how many keys an edge goes to, and which key owns an instance."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifscan.functions.buckets import bucket_of, pack_tuple, rank_multiset, rank_three
from motifscan.plans.patterns import Pattern


def multiset_keys(edges: DataFrame, b: int, p: int, kind: str = "xx", seed: int = 0) -> DataFrame:
    """Bucket-oriented: rows (rk, src, dst), each edge with every list of p - 2 more buckets. C(b+p-3, p-2) rows an edge."""
    if p == 3:
        rows = edges.select("src", "dst", bucket_of("src", b, kind, seed).alias("u"), bucket_of("dst", b, kind, seed).alias("v"), F.explode(F.sequence(F.lit(0), F.lit(b - 1))).alias("w"))
        return rows.select(rank_three(F.col("u"), F.col("v"), F.col("w")).alias("rk"), "src", "dst")
    rows = edges.select("src", "dst", F.array(bucket_of("src", b, kind, seed), bucket_of("dst", b, kind, seed)).alias("list"), F.lit(0).alias("w"))
    for _ in range(p - 2):  # one more bucket, none below the last one that was added
        rows = rows.select("src", "dst", "list", F.explode(F.sequence("w", F.lit(b - 1))).alias("w")).select("src", "dst", F.concat("list", F.array("w")).alias("list"), "w")
    return rows.select(rank_multiset(F.col("list"), b, p).alias("rk"), "src", "dst")


def group_bit(group: Column) -> Column:
    """One bit for a group, of up to 62."""
    return F.call_function("shiftleft", F.lit(1).cast("long"), group)


def nodeset_keys(edges: DataFrame, b: int, p: int, kind: str = "xx", seed: int = 0) -> DataFrame:
    """Node-set partition: rows (rk, src, dst), each edge with every p-subset of groups that holds both ends' groups; rk has a bit for each group."""
    if not p <= b <= 62:
        raise ValueError(f"node sets need at least as many groups ({b}) as pattern nodes ({p}), and at most 62")
    u, v = bucket_of("src", b, kind, seed), bucket_of("dst", b, kind, seed)
    every = F.sequence(F.lit(0), F.lit(b - 1))
    # an edge within a group takes any other group for its second; further groups rise, from behind that one
    second = F.when(F.col("u") != F.col("v"), F.array("v")).otherwise(F.filter(every, lambda x: x != F.col("u")))
    rows = edges.select("src", "dst", u.alias("u"), v.alias("v")).select("src", "dst", "u", "v", F.explode(second).alias("s"))
    rows = rows.select("src", "dst", "u", "s", group_bit(F.col("u")).bitwiseOR(group_bit(F.col("s"))).alias("rk"), F.when(F.col("u") == F.col("v"), F.col("s")).otherwise(-1).alias("last"))
    for _ in range(p - 2):
        more = F.filter(every, lambda x: (x > F.col("last")) & (x != F.col("u")) & (x != F.col("s")))
        rows = rows.select("src", "dst", "u", "s", "rk", F.explode(more).alias("last")).withColumn("rk", F.col("rk").bitwiseOR(group_bit(F.col("last"))))
    return rows.select("rk", "src", "dst")


def nodeset_owner(names: Sequence[str], b: int, kind: str = "xx", seed: int = 0) -> Column:
    """The least subset of groups, as bits, that holds the groups of all nodes: these, and the lowest others."""
    own = F.array_distinct(F.array(*(bucket_of(n, b, kind, seed) for n in names)))
    others = F.array_except(F.sequence(F.lit(0), F.lit(b - 1)), own)
    return F.aggregate(F.concat(own, F.slice(others, 1, F.lit(len(names)) - F.size(own))), F.lit(0).cast("long"), lambda acc, x: acc.bitwiseOR(group_bit(x)))


def free_keys(rows: DataFrame, shares: Sequence[int], free: Sequence[int]) -> DataFrame:
    """Adds to the column rk what the free variables' buckets add, a row for each of their combinations."""
    for v in free:
        if shares[v] > 1:
            weight = math.prod(shares[v + 1 :])
            others = [c for c in rows.columns if c != "rk"]
            rows = rows.select(*others, "rk", F.explode(F.sequence(F.lit(0), F.lit(shares[v] - 1))).alias("_w")).select(*others, (F.col("rk") + F.col("_w") * weight).alias("rk"))
    return rows


def variable_keys(edges: DataFrame, s: Pattern, shares: Sequence[int], directions: dict[tuple[int, int], tuple[bool, bool]], kind: str = "xx", seed: int = 0) -> DataFrame:
    """Variable-oriented: rows (rk, role, src, dst). For each subgoal and direction in use, an edge fixes two variables' buckets and goes to all of the others'. role: 2 * subgoal, and 1 more for the reversed direction."""
    out = None
    for n, (a, b) in enumerate(s.edges):
        for reverse in (False, True):
            if not directions[(a, b)][reverse]:
                continue
            at = {b: "src", a: "dst"} if reverse else {a: "src", b: "dst"}
            fixed = sum((bucket_of(at[v], shares[v], kind, seed + v).cast("long") * math.prod(shares[v + 1 :]) for v in (a, b)), F.lit(0).cast("long"))
            rows = edges.select("src", "dst", F.lit(2 * n + reverse).cast("byte").alias("role"), fixed.alias("rk"))
            rows = free_keys(rows, shares, [v for v in range(s.p) if v not in (a, b)]).select("rk", "role", "src", "dst")
            out = rows if out is None else out.unionByName(rows)
    return out


def tuple_owner(s: Pattern, shares: Sequence[int], names: Sequence[str], kind: str = "xx", seed: int = 0) -> Column:
    """The key of an instance under variable_keys."""
    return pack_tuple([bucket_of(names[v], shares[v], kind, seed + v) for v in range(s.p)], shares)


def multiset_owner(names: Sequence[str], b: int, kind: str = "xx", seed: int = 0) -> Column:
    if len(names) == 3:
        return rank_three(*(bucket_of(n, b, kind, seed) for n in names))
    return rank_multiset(F.array(*(bucket_of(n, b, kind, seed) for n in names)), b, len(names))

