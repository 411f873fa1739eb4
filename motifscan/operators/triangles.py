"""Triangles: three one-round schemes, the degree-ordered join, and the baselines. All return x0 < x1 < x2 (longs) unless stated."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifscan.functions.buckets import bucket_of, pack_tuple
from motifscan.operators import schemes
from motifscan.operators.closing import closed, neighbour_lists, sieve
from motifscan.operators.rounds import one_round
from motifscan.sources.graphs import DataGraph
from motifscan.sources.tables import kept

X = ["x0", "x1", "x2"]


def _join(xy: DataFrame, yz: DataFrame, xz: DataFrame) -> DataFrame:
    """Three edge tables with a key each; edges (x, y), (y, z), (x, z)."""
    a = xy.select("rk", F.col("src").alias("x0"), F.col("dst").alias("x1"))
    b = yz.select("rk", F.col("src").alias("x1"), F.col("dst").alias("x2"))
    c = xz.select("rk", F.col("src").alias("x0"), F.col("dst").alias("x2"))
    return a.join(b, ["rk", "x1"]).join(c, ["rk", "x0", "x2"])


def multiway_pairs(g: DataGraph, b: int, dedup_pairs: bool = False, kind: str = "xx", seed: int = 0) -> DataFrame:
    """(rk, roles, src, dst): an edge plays xy, yz and xz, each for every bucket of the node it lacks; roles has a bit each. dedup_pairs: equal keys of an edge are merged."""
    u, v = bucket_of("src", b, kind, seed), bucket_of("dst", b, kind, seed)
    free = F.sequence(F.lit(0), F.lit(b - 1))
    role = lambda bit, k: F.transform(free, lambda w: F.struct(pack_tuple(k(w), [b] * 3).alias("rk"), F.lit(bit).alias("role")))
    every = F.concat(role(1, lambda w: [u, v, w]), role(2, lambda w: [w, u, v]), role(4, lambda w: [u, w, v]))
    rows = g.edges.select("src", "dst", F.explode(every).alias("k")).select("k.rk", "k.role", "src", "dst")
    if not dedup_pairs:
        return rows.withColumnRenamed("role", "roles")
    k = F.col("every")
    merged = F.transform(F.array_distinct(F.transform(k, lambda x: x["rk"])), lambda rk: F.struct(rk.alias("rk"), F.aggregate(F.filter(k, lambda x: x["rk"] == rk), F.lit(0), lambda s, x: s + x["role"]).alias("roles")))
    return g.edges.select("src", "dst", every.alias("every")).select("src", "dst", F.explode(merged).alias("k")).select("k.rk", "k.roles", "src", "dst")


def triangles_multiway(g: DataGraph, b: int, dedup_pairs: bool = False, kind: str = "xx") -> DataFrame:
    """One-round cyclic join: only the key of a triangle's own three buckets has its edges in their roles."""
    rows = multiway_pairs(g, b, dedup_pairs, kind).repartition("rk")
    of = lambda bit: rows.where(F.col("roles").bitwiseAND(bit) != 0)
    return one_round(_join(of(1), of(2), of(4)).select(*X))


def triangles_ordered(g: DataGraph, b: int, kind: str = "xx") -> DataFrame:
    """Bucket lists without regard to order: an edge goes to b keys, and a triangle is reported by the key that is its own buckets."""
    rows = schemes.multiset_keys(g.edges, b, 3, kind).repartition("rk")
    found = _join(rows, rows, rows)
    return one_round(found.where(schemes.multiset_owner(X, b, kind) == F.col("rk")).select(*X))


def triangles_nodeset(g: DataGraph, b: int, dedup: str = "owner", kind: str = "xx") -> DataFrame:
    """Subsets of three of b groups. A triangle within fewer groups is found at several keys: reported by the least ('owner'), by a distinct ('distinct'), as often as found ('none'), or as often as found with the inverse of that as its weight ('weight': a column more; the weights' sum is the count)."""
    rows = schemes.nodeset_keys(g.edges, b, 3, kind).repartition("rk")
    return one_round(nodeset_remedy(_join(rows, rows, rows), X, b, dedup, kind))


def nodeset_remedy(found: DataFrame, names: list[str], b: int, dedup: str, kind: str = "xx") -> DataFrame:
    """What becomes of instances that several subsets of groups find."""
    p = len(names)
    if dedup == "owner":
        return found.where(schemes.nodeset_owner(names, b, kind) == F.col("rk")).select(*names)
    if dedup == "distinct":
        return found.select(*names).distinct()
    if dedup == "none":
        return found.select(*names)
    if dedup == "weight":
        groups = F.size(F.array_distinct(F.array(*(bucket_of(n, b, kind) for n in names))))
        times = F.array(*(F.lit(float(math.comb(b - i, p - i))) for i in range(1, p + 1)))
        return found.select(*names, (F.lit(1.0) / F.element_at(times, groups)).alias("weight"))
    raise ValueError(f"no such remedy: {dedup}")


def nodeset_multiplicity(g: DataGraph, b: int, kind: str = "mod") -> DataFrame:
    """(n_groups, instances, found, formula): triangles by the number of groups they lie in, how often they are found, and C(b - g, 3 - g) times instances."""
    found = triangles_nodeset(g, b, "none", kind).groupBy(*X).agg(F.count("*").alias("times"))
    groups = F.size(F.array_distinct(F.array(*(bucket_of(n, b, kind) for n in X)))).cast("long")
    times = F.element_at(F.array(*(F.lit(math.comb(b - i, 3 - i)).cast("long") for i in (1, 2, 3))), F.col("n_groups").cast("int"))
    return found.withColumn("n_groups", groups).groupBy("n_groups").agg(F.count("*").alias("instances"), F.sum("times").alias("found")).withColumn("formula", F.col("instances") * times)


def degree_ordered(g: DataGraph) -> DataFrame:
    """(lo, hi, lo_degree, hi_degree): each edge from the end of the smaller (degree, id) to the other."""
    d = g.degrees()
    e = g.edges.join(d.toDF("src", "ds"), "src").join(d.toDF("dst", "dd"), "dst")
    first = F.struct("ds", "src") < F.struct("dd", "dst")
    pick = lambda a, b: F.when(first, F.col(a)).otherwise(F.col(b))
    return e.select(pick("src", "dst").alias("lo"), pick("dst", "src").alias("hi"), pick("ds", "dd").alias("lo_degree"), pick("dd", "ds").alias("hi_degree"))


def ordered_two_paths(g: DataGraph) -> DataFrame:
    """(v, u, w), u < w by id: paths u - v - w whose middle comes before both ends in degree order. Out-degrees are at most the root of 2m, so hubs don't blow up."""
    o = degree_ordered(g).select("lo", "hi")
    a, b = o.toDF("v", "u"), o.toDF("v", "w")
    return a.join(b, "v").where("u < w").select("v", "u", "w")


def degree_split(g: DataGraph) -> DataFrame:
    """(node, degree, high): high nodes have at least the root of m edges; there are at most twice that many."""
    m = g.edges.agg(F.count("*").alias("m"))
    return g.degrees().join(F.broadcast(m)).select("node", "degree", (F.col("degree") >= F.sqrt("m")).alias("high"))


def triangles_by_degree(g: DataGraph) -> DataFrame:
    """Two-paths closed by an edge."""
    e = g.edges.toDF("u", "w")
    closed = ordered_two_paths(g).join(e, ["u", "w"], "left_semi")
    s = F.array_sort(F.array("v", "u", "w"))
    return closed.select(*(s[i].alias(X[i]) for i in range(3)))


def triangles_cascade(g: DataGraph) -> DataFrame:
    """Baseline: two joins, each with its own shuffle."""
    e = g.edges
    return e.toDF("x0", "x1").join(e.toDF("x1", "x2"), "x1").join(e.toDF("x0", "x2"), ["x0", "x2"]).select(*X)


def triangles_undirected(g: DataGraph) -> DataFrame:
    """Baseline: every triangle in all six mappings."""
    e = g.both_ways()
    return e.toDF("x0", "x1").join(e.toDF("x1", "x2"), "x1").join(e.toDF("x0", "x2"), ["x0", "x2"]).select(*X)


def odd_cycles(g: DataGraph, length: int) -> DataFrame:
    """(x0..): each cycle of an odd length once, by joins: two arms from the cycle's first node in degree order grow along later nodes and meet there, and an edge between their ends closes them. An arm's last nodes are lists, so that its paths aren't shipped one by one."""
    if length < 3 or length % 2 == 0:
        raise ValueError(f"{length} isn't an odd length of a cycle")
    if length == 3:
        return ordered_two_paths(g).join(g.edges.toDF("u", "w"), ["u", "w"], "left_semi").select(F.col("v").alias("x0"), F.col("u").alias("x1"), F.col("w").alias("x2"))
    e, k = DataGraph(kept(g.edges, "edges")), length // 2
    o = degree_ordered(e)
    ways = F.explode(F.array(F.struct(F.col("lo").alias("at"), F.struct(F.col("hi_degree").alias("d"), F.col("hi").alias("v")).alias("to")), F.struct(F.col("hi").alias("at"), F.struct(F.col("lo_degree").alias("d"), F.col("lo").alias("v")).alias("to"))))
    both = o.select(ways.alias("e")).select("e.at", "e.to")
    first = F.struct(F.col("d0").alias("d"), F.col("x0").alias("v"))
    arm = o.select(F.col("lo").alias("x0"), F.col("lo_degree").alias("d0"), F.col("hi").alias("n1"))
    for i in range(2, k):
        grown = arm.join(both.withColumnRenamed("at", f"n{i - 1}"), f"n{i - 1}").where(F.col("to") > first)
        arm = grown.select("x0", "d0", *(f"n{j}" for j in range(1, i)), F.col("to.v").alias(f"n{i}"))
        for j in range(1, i - 1):
            arm = arm.where(F.col(f"n{j}") != F.col(f"n{i}"))
    later = F.transform(F.filter("ends", lambda x: x > first), lambda x: x["v"])
    inner = [f"n{j}" for j in range(1, k)]
    arm = arm.join(neighbour_lists(both).withColumnRenamed("at", f"n{k - 1}"), f"n{k - 1}").select("x0", *inner, later.alias("ends")).where(F.size("ends") > 0).repartition("x0")
    one, two = ([f"{side}{j}" for j in range(1, k + 1)] for side in "ab")
    df = arm.toDF("x0", *one[:-1], "one").join(arm.toDF("x0", *two[:-1], "two"), "x0").where(F.col(one[0]) < F.col(two[0]))
    differ = lambda df, v, others: df.where(~F.col(v).isin(*(F.col(c) for c in others))) if others else df
    for v in one[1:-1]:
        df = differ(df, v, two[:-1])
    if k > 2:
        df = differ(df, one[0], two[1:-1])
    df = differ(df.withColumn(one[-1], F.explode("one")).drop("one"), one[-1], one[:-1] + two[:-1])
    df = differ(df.withColumn(two[-1], F.explode("two")).drop("two"), two[-1], one + two[:-1])
    ends = (F.least(one[-1], two[-1]).alias("src"), F.greatest(one[-1], two[-1]).alias("dst"))
    found = closed(df.select("x0", *one, *two, *ends), "src", "dst", e.edges, sieve(e.edges))
    return found.select(*(F.col(c).alias(f"x{i}") for i, c in enumerate(["x0", *one, *two[::-1]])))
