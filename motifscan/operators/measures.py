"""Measured costs: shipped pairs, load of keys, repeated and missing instances; and comparisons of schemes."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifscan.operators import schemes
from motifscan.operators.reduce import probe_counts
from motifscan.operators.triangles import multiway_pairs
from motifscan.plans import costs
from motifscan.plans import shares as sh
from motifscan.plans.cqs import MotifQuery
from motifscan.plans.patterns import Pattern
from motifscan.sources.graphs import DataGraph


def load_per_key(rows: DataFrame) -> DataFrame:
    """(rk, edges, nodes): different edges and nodes of each key."""
    ends = rows.select("rk", "src", "dst").distinct()
    nodes = ends.select("rk", F.explode(F.array("src", "dst")).alias("v")).groupBy("rk").agg(F.countDistinct("v").alias("nodes"))
    return ends.groupBy("rk").agg(F.count("*").alias("edges")).join(nodes, "rk")


def shipped(g: DataGraph, scheme: str, b: int, p: int = 3, kind: str = "xx") -> DataFrame:
    if scheme in ("multiway", "multiway_dedup"):
        return multiway_pairs(g, b, scheme == "multiway_dedup", kind)
    if scheme == "nodeset":
        return schemes.nodeset_keys(g.edges, b, p, kind)
    return schemes.multiset_keys(g.edges, b, p, kind)


def cost_rows(g: DataGraph, scheme: str, b: int, p: int = 3, kind: str = "xx") -> DataFrame:
    """One row: scheme, b, pairs, keys_hit, max_load (pairs of a key)."""
    load = shipped(g, scheme, b, p, kind).groupBy("rk").agg(F.count("*").alias("c"))
    return load.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("pairs"), F.count("*").alias("keys_hit"), F.coalesce(F.max("c"), F.lit(0)).alias("max_load")).select(F.lit(scheme).alias("scheme"), F.lit(b).cast("long").alias("b"), "pairs", "keys_hit", "max_load")


def measure(g: DataGraph, scheme: str, b: int, s: Pattern, kind: str = "xx") -> costs.CostReport:
    """One row of figures, collected."""
    row = cost_rows(g, scheme, b, s.p, kind).first()
    m = g.edges.count()
    formula = {"multiway": lambda: costs.multiway_pairs(b), "multiway_dedup": lambda: costs.multiway_pairs(b, True), "nodeset": lambda: costs.nodeset_pairs(b, s.p)}.get(scheme, lambda: costs.bucket_pairs(b, s.p))()
    k = costs.keys("multiway" if scheme.startswith("multiway") else "nodeset" if scheme == "nodeset" else "bucket", b, s.p)
    return costs.CostReport(scheme, s.name, b, k, m, row["pairs"], row["keys_hit"], row["max_load"], row["pairs"] / max(1, m), row["pairs"] / max(1, row["keys_hit"]), float(formula))


def compare_schemes(g: DataGraph, s: Pattern, k: int) -> list[costs.CostReport]:
    """Each scheme at the largest b whose keys are at most k."""
    out = []
    for scheme in ("nodeset", "multiway_dedup", "bucket") if s.p == 3 else ("nodeset", "bucket"):
        name = "multiway" if scheme.startswith("multiway") else scheme
        b = max((b for b in range(s.p, 200) if costs.keys(name, b, s.p) <= k), default=s.p)
        out.append(measure(g, scheme, b, s))
    return out


def load_summary(rows: DataFrame) -> DataFrame:
    """One row: keys, mean, p50, p99 and max of the rows of a key, and skew, the largest load over the mean."""
    load = rows.groupBy("rk").agg(F.count("*").alias("c"))
    out = load.agg(F.count("*").alias("keys"), F.avg("c").alias("mean"), F.percentile("c", 0.5).alias("p50"), F.percentile("c", 0.99).alias("p99"), F.max("c").alias("max"))
    return out.withColumn("skew", F.col("max") / F.col("mean"))


def convertible_work(g: DataGraph, s: Pattern, b: int | Sequence[int], algorithm: str = "grow", kind: str = "xx") -> DataFrame:
    """(b, probes) over all keys, a row for each b. Against b = 1 it stays within a constant factor if the algorithm is convertible."""
    out = None
    for n in (b,) if isinstance(b, int) else b:
        row = probe_counts(schemes.multiset_keys(g.edges, n, s.p, kind), s, algorithm).agg(F.lit(n).cast("long").alias("b"), F.coalesce(F.sum("probes"), F.lit(0)).alias("probes"))
        out = row if out is None else out.unionByName(row)
    return out


def sweep(g: DataGraph, points: Sequence[tuple[str, int, int]], kind: str = "xx") -> DataFrame:
    """cost_rows, and pattern nodes p, of each (scheme, b, p): how communication, keys and the largest load move with b."""
    out = None
    for scheme, b, p in points:
        row = cost_rows(g, scheme, b, p, kind).withColumn("p", F.lit(p).cast("long"))
        out = row if out is None else out.unionByName(row)
    return out


def share_pairs(g: DataGraph, s: Pattern, k: float, queries: Sequence[MotifQuery]) -> DataFrame:
    """One row: k (the product of the whole shares), pairs shipped for these queries together."""
    ts = sh.terms(s, list(queries))
    shares = sh.round_shares(s.p, ts, sh.optimise(s.p, ts, k), k)
    used = {e for q in queries for e in q.subgoals}
    rows = schemes.variable_keys(g.edges, s, shares, {(a, b): ((a, b) in used, (b, a) in used) for a, b in s.edges})
    return rows.agg(F.lit(math.prod(shares)).cast("long").alias("k"), F.count("*").alias("pairs"))


def grouping_pairs(g: DataGraph, s: Pattern, k: float, queries: Sequence[MotifQuery]) -> DataFrame:
    """(evaluation, jobs, pairs): all queries in one job, and a job of k keys for each, as shipped."""
    joint = share_pairs(g, s, k, queries).select(F.lit("joint").alias("evaluation"), F.lit(1).cast("long").alias("jobs"), "pairs")
    each = None
    for q in queries:
        row = share_pairs(g, s, k, [q]).select("pairs")
        each = row if each is None else each.unionByName(row)
    return joint.unionByName(each.agg(F.lit("separate").alias("evaluation"), F.count("*").alias("jobs"), F.sum("pairs").alias("pairs")))


def shipped_by_plan(g: DataGraph, b: int) -> DataFrame:
    """(plan, rows) that triangles need shipped: by two-way joins one after the other (both sides of each), by joins along degree order, and in one round of b buckets."""
    from motifscan.operators.triangles import ordered_two_paths

    m = g.edges.agg(F.count("*").alias("m"))
    paths = g.edges.groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("i")).join(g.edges.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("o")), "v").agg(F.coalesce(F.sum(F.col("i") * F.col("o")), F.lit(0)).alias("paths"))
    ordered = ordered_two_paths(g).agg(F.count("*").alias("ordered"))
    one = m.crossJoin(paths).crossJoin(ordered)  # three rows of one row each
    return one.select(F.stack(F.lit(3), F.lit("cascade"), 3 * F.col("m") + F.col("paths"), F.lit("degree"), 3 * F.col("m") + F.col("ordered"), F.lit("one_round"), F.lit(b) * F.col("m")).alias("plan", "rows"))


def bounds(g: DataGraph, counts: DataFrame, sizes: dict[str, int]) -> DataFrame:
    """(pattern, n, of_bound, of_degree_bound): instances over m^(p/2), and over m * max_degree^(p - 2). counts: (pattern, n); sizes: nodes of each pattern."""
    p = F.create_map(*(F.lit(x) for kv in sizes.items() for x in kv))[F.col("pattern")]
    stats = g.stats().select(F.col("m").cast("double").alias("m"), F.col("max_degree").cast("double").alias("d"))
    both = counts.join(F.broadcast(stats))  # one row
    return both.select("pattern", "n", (F.col("n") / F.pow("m", p / 2)).alias("of_bound"), (F.col("n") / (F.col("m") * F.pow("d", p - 2))).alias("of_degree_bound"))


def discoveries(instances: DataFrame) -> DataFrame:
    """(times, instances): how many instances were found so often. All once is one row with times 1."""
    return instances.groupBy(*instances.columns).agg(F.count("*").alias("times")).groupBy("times").agg(F.count("*").alias("instances"))


def completeness(found: DataFrame, expected: DataFrame) -> DataFrame:
    """One row: expected, missing, extra."""
    cols = expected.columns
    missing = expected.join(found.select(*cols).distinct(), cols, "left_anti").agg(F.count("*").alias("missing"))
    extra = found.select(*cols).join(expected, cols, "left_anti").agg(F.count("*").alias("extra"))
    return expected.agg(F.count("*").alias("expected")).join(missing).join(extra)


def output_ratio(instances: int, p: int, m: int) -> float:
    return instances / max(1.0, costs.output_bound(p, m))


def exact_key_load(g: DataGraph, b: int, p: int, kind: str = "xx") -> dict[tuple[int, ...], int]:
    """Edges of every key from the b^2 counts of bucket pairs, without shipping anything."""
    import itertools

    from motifscan.functions.buckets import bucket_of

    u, v = bucket_of("src", b, kind), bucket_of("dst", b, kind)
    pairs = {(r["u"], r["v"]): r["count"] for r in g.edges.select(F.least(u, v).alias("u"), F.greatest(u, v).alias("v")).groupBy("u", "v").count().collect()}
    out = {}
    for key in itertools.combinations_with_replacement(range(b), p):
        out[key] = sum(n for (a, c), n in pairs.items() if a in key and c in key and (a != c or key.count(a) >= 1) and (a == c and key.count(a) >= 2 or a != c))
    return out


def reducers_for_memory(m: int, p: int, edges_per_key: float) -> int:
    """The least b whose mean load is within a budget: about m p (p - 1) / b^2 edges a key."""
    return max(1, math.ceil(math.sqrt(m * p * (p - 1) / edges_per_key)))
