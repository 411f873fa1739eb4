"""Instances of any pattern: one-round schemes and baselines. Columns x0..x{p-1}, the least of each instance's mappings."""

from __future__ import annotations

import itertools
import math
import warnings
from collections.abc import Sequence

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifscan.functions.buckets import canonical_mapping, is_canonical, pairs_condition
from motifscan.operators import schemes, triangles
from motifscan.operators.closing import closed, neighbour_lists, sieve
from motifscan.operators.reduce import Lists, Subsets, reduce_by_key
from motifscan.operators.rounds import guarded_cross, one_round
from motifscan.operators.triangles import nodeset_remedy
from motifscan.plans import shares as sh
from motifscan.plans.cqs import MotifQuery, cqs_by_orientation
from motifscan.plans.patterns import Pattern
from motifscan.plans.planner import cheapest_queries, plan
from motifscan.sources.graphs import DataGraph
from motifscan.sources.tables import kept


def names(s: Pattern) -> list[str]:
    return [f"x{i}" for i in range(s.p)]


def condition(q: MotifQuery) -> Column:
    """A query's conditions on the columns x0.."""
    x = [f"x{i}" for i in range(q.p)]
    out = pairs_condition((*q.subgoals, *q.less), x)
    for a, b in q.differ:
        out = out & (F.col(x[a]) != F.col(x[b]))
    if q.orders:
        any_of = F.lit(False)
        for o in q.orders:
            any_of = any_of | pairs_condition(tuple(zip(o, o[1:], strict=False)), x)
        out = out & any_of
    return out


def _counted(df: DataFrame, count_only: bool) -> DataFrame:
    return df.agg(F.count("*").alias("n")) if count_only else df


def _bound_early(df: DataFrame, q: MotifQuery, bound: list[int], new: int) -> DataFrame:
    """The conditions that a newly bound variable decides."""
    for a, b in (*q.subgoals, *q.less):
        if new in (a, b) and a in bound and b in bound:
            df = df.where(F.col(f"x{a}") < F.col(f"x{b}"))
    for a, b in q.differ:
        if new in (a, b) and a in bound and b in bound:
            df = df.where(F.col(f"x{a}") != F.col(f"x{b}"))
    return df


def join_query(q: MotifQuery, edges_of: dict[tuple[int, int], DataFrame], key: Sequence[str] = (), share: dict[tuple, DataFrame] | None = None) -> DataFrame:
    """A query's joins: edges_of[(a, b)] has src, dst and the key columns of the subgoal. Conditions apply as soon as their variables are bound. share: joins of other queries that began alike."""
    left = list(q.subgoals)
    a, b = left.pop(0)
    df = edges_of[(a, b)].select(*key, F.col("src").alias(f"x{a}"), F.col("dst").alias(f"x{b}"))
    bound = [a, b]
    df = _bound_early(df, q, bound, b)
    done = [(a, b)]
    while left:
        nxt = next((e for e in left if e[0] in bound and e[1] in bound), None) or next((e for e in left if e[0] in bound or e[1] in bound), left[0])
        left.remove(nxt)
        a, b = nxt
        e = edges_of[(a, b)].select(*key, F.col("src").alias(f"x{a}"), F.col("dst").alias(f"x{b}"))
        shared = [f"x{v}" for v in nxt if v in bound]
        df = df.join(e, [*key, *shared]) if shared or key else guarded_cross(df, e)
        for v in nxt:
            if v not in bound:
                bound.append(v)
                df = _bound_early(df, q, bound, v)
        done.append(nxt)
        if share is not None and left:
            inside = lambda pairs: tuple(sorted(c for c in pairs if set(c) <= set(bound)))
            # the joins so far and the conditions that were applied to them
            begun = (tuple(done), inside(q.less), inside(q.differ))
            if begun not in share:
                share[begun] = df.persist(StorageLevel.DISK_ONLY)
            df = share[begun]
    return df.where(condition(q))


def enumerate_bucket_oriented(g: DataGraph, s: Pattern, b: int, kind: str = "xx", algorithm: str = "grow", count_only: bool = False, queries: list[MotifQuery] | None = None) -> DataFrame:
    """The same b for all variables, a key for each list of p buckets; each edge once, in one direction. One exchange; a serial algorithm, or all of the queries, at each key, which reports what the key owns. count_only: counted there."""
    return reduce_by_key(schemes.multiset_keys(g.edges, b, s.p, kind), s, algorithm, Lists(b, kind), count_only, queries=queries)


def enumerate_bucket_joins(g: DataGraph, s: Pattern, b: int, kind: str = "xx", queries: list[MotifQuery] | None = None, count_only: bool = False) -> DataFrame:
    """The same keys, evaluated by joins of each query at each key, inside the JVM. One exchange."""
    rows = schemes.multiset_keys(g.edges, b, s.p, kind).repartition("rk")
    out = None
    for q in queries or cqs_by_orientation(s):
        found = join_query(q, {e: rows for e in q.subgoals}, ["rk"])
        found = found.where(schemes.multiset_owner(names(s), b, kind) == F.col("rk")).select(*canonical_mapping(s, names(s)))
        out = found if out is None else out.unionByName(found)
    return one_round(_counted(out, count_only))


def enumerate_nodeset(g: DataGraph, s: Pattern, b: int, dedup: str = "owner", kind: str = "xx", algorithm: str = "grow", count_only: bool = False) -> DataFrame:
    """Baseline: subsets of p of b groups; dedup as for triangles."""
    rows = schemes.nodeset_keys(g.edges, b, s.p, kind)
    if dedup == "owner":
        return reduce_by_key(rows, s, algorithm, Subsets(b, kind), count_only)
    out = nodeset_remedy(reduce_by_key(rows, s, algorithm, with_key=True), names(s), b, dedup, kind)
    return out.agg(F.round(F.sum("weight")).cast("long").alias("n")) if count_only and dedup == "weight" else _counted(out, count_only)


def _whole_shares(s: Pattern, queries: list[MotifQuery], k: float) -> list[int]:
    ts = sh.terms(s, queries)
    return sh.round_shares(s.p, ts, sh.optimise(s.p, ts, k), k)


def enumerate_variable_oriented(g: DataGraph, s: Pattern, k: int, shares: Sequence[int] | None = None, queries: list[MotifQuery] | None = None, kind: str = "xx", count_only: bool = False) -> DataFrame:
    """A share for each variable, all queries at each key; an edge is shipped for each subgoal in the directions that some query uses, in one exchange for each of these relations."""
    queries = queries or cqs_by_orientation(s, "bidirectional")
    shares = shares or _whole_shares(s, queries, k)
    used = {e for q in queries for e in q.subgoals}
    directions = {(a, b): ((a, b) in used, (b, a) in used) for a, b in s.edges}
    rows = schemes.variable_keys(g.edges, s, shares, directions, kind).repartition("rk")
    out = None
    for q in queries:
        of = {}
        for a, b in q.subgoals:
            n = s.edges.index((min(a, b), max(a, b)))
            of[(a, b)] = rows.where(F.col("role") == 2 * n + (a > b))
        # role-wise rows meet at the instance's own key only
        found = join_query(q, of, ["rk"]).select(*canonical_mapping(s, names(s)))
        out = found if out is None else out.unionByName(found)
    return one_round(_counted(out, count_only))


def enumerate_cq_oriented(g: DataGraph, s: Pattern, k: int, queries: list[MotifQuery] | None = None, kind: str = "xx", count_only: bool = False) -> DataFrame:
    """Baseline: a job for each query, with shares that are best for it alone."""
    out = None
    for q in queries or cqs_by_orientation(s):
        found = enumerate_variable_oriented(g, s, k, queries=[q], kind=kind)
        out = found if out is None else out.unionByName(found)
    return one_round(_counted(out, count_only))


def enumerate_undirected(g: DataGraph, s: Pattern, k: int, kind: str = "xx", count_only: bool = False) -> DataFrame:
    """One join in which every edge plays both directions of every subgoal, and the order only selects at the end."""
    ts = tuple(sh.Term(a, b, 2.0) for a, b in s.edges)
    shares = sh.round_shares(s.p, ts, sh.optimise(s.p, ts, k), k)
    rows = schemes.variable_keys(g.edges, s, shares, {e: (True, True) for e in s.edges}, kind)
    turned = rows.select("rk", F.floor(F.col("role") / 2).alias("subgoal"), F.when(F.col("role") % 2 == 1, F.col("dst")).otherwise(F.col("src")).alias("src"), F.when(F.col("role") % 2 == 1, F.col("src")).otherwise(F.col("dst")).alias("dst")).repartition("rk")
    free = MotifQuery(s.p, (), (), tuple((a, b) for a in range(s.p) for b in range(a + 1, s.p)))
    found = _all_mappings(s, free, {e: turned.where(F.col("subgoal") == n) for n, e in enumerate(s.edges)}, ["rk"]).where(is_canonical(s, names(s))).select(*names(s))
    return one_round(_counted(found, count_only))


def _all_mappings(s: Pattern, q: MotifQuery, of: dict[tuple[int, int], DataFrame], key: Sequence[str] = ()) -> DataFrame:
    """Joins along the pattern's edges, without order."""
    df, bound, left = None, [], list(s.edges)
    while left:
        e = left[0] if df is None else next((x for x in left if x[0] in bound and x[1] in bound), None) or next((x for x in left if x[0] in bound or x[1] in bound), left[0])
        left.remove(e)
        rows = of[e].select(*key, F.col("src").alias(f"x{e[0]}"), F.col("dst").alias(f"x{e[1]}"))
        shared = [f"x{v}" for v in e if v in bound]
        df = rows if df is None else df.join(rows, [*key, *shared]) if shared or key else guarded_cross(df, rows)
        for v in e:
            if v not in bound:
                bound.append(v)
                df = _bound_early(df, q, bound, v)
    return df


def enumerate_all_mappings(g: DataGraph, s: Pattern, count_only: bool = False) -> DataFrame:
    """Baseline: every mapping of every instance, as many as the pattern has symmetries. A square's are pairs of two-paths between its opposite nodes, so that no path of three edges is shipped."""
    if s.p == 4 and len(s.edges) == 4 and all(len(s.neighbours(v)) == 2 for v in range(4)) and not s.directed:
        return _counted(_square_mappings(g, s), count_only)
    both = g.both_ways().toDF("src", "dst")
    free = MotifQuery(s.p, (), (), tuple((a, b) for a in range(s.p) for b in range(a + 1, s.p)))
    return _counted(_all_mappings(s, free, {e: both for e in s.edges}).select(*names(s)), count_only)


def _square_mappings(g: DataGraph, s: Pattern) -> DataFrame:
    opposite = next(v for v in range(1, 4) if v not in s.neighbours(0))
    one, two = (f"x{v}" for v in sorted(s.neighbours(0)))
    both = g.both_ways()
    paths = both.toDF("m", "a").join(both.toDF("m", "c"), "m").where("a < c").select("a", "c", "m")
    found = paths.withColumnRenamed("m", one).join(paths.withColumnRenamed("m", two), ["a", "c"]).where(F.col(one) != F.col(two))
    ends = F.explode(F.array(F.struct(F.col("a").alias("x0"), F.col("c").alias(f"x{opposite}")), F.struct(F.col("c").alias("x0"), F.col("a").alias(f"x{opposite}"))))
    return found.select(one, two, ends.alias("e")).select(one, two, "e.*").select(*names(s))


def _open_at(q: MotifQuery, known: set[tuple[bool, ...]]) -> tuple[list[int], list[tuple[bool, ...]]]:
    """An odd cycle's nodes from one end to the other of the edge that closes it, and of the two arms from the middle whether each step is up: the edge without which the fewest node orders are left, then the fewest arms that aren't known yet."""
    best = None
    for last in q.subgoals:
        rest = [e for e in q.subgoals if e != last]
        path = [last[0]]
        while len(path) < q.p:
            path.append(next(v for e in rest if path[-1] in e for v in e if v not in path))
        orders = sum(all(o[a] < o[b] for a, b in rest) for o in itertools.permutations(range(q.p)))
        arms = [tuple((u, v) in q.subgoals for u, v in zip(arm, arm[1:], strict=False)) for arm in (path[q.p // 2 :: -1], path[q.p // 2 :])]
        cost = (orders, len(set(arms) - known))
        if best is None or cost < best[0]:
            best = cost, path, arms
    return best[1], best[2]


def _odd_cycle_cascade(g: DataGraph, s: Pattern, queries: list[MotifQuery]) -> DataFrame:
    """Each query of an odd cycle as two arms that are joined in the cycle's middle, and closed by the edge between their ends. Arms end in lists, and queries share them."""
    e, k, out = DataGraph(kept(g.edges, "edges")), s.p // 2, None
    arcs = {True: e.edges.toDF("at", "to"), False: e.edges.select(F.col("dst").alias("at"), F.col("src").alias("to"))}
    arms: dict[tuple[bool, ...], DataFrame] = {}
    sifted = sieve(e.edges)

    def arm(ups: tuple[bool, ...]) -> DataFrame:
        if ups not in arms:
            df = arcs[ups[0]].toDF("n0", "n1")
            for i in range(2, k):
                df = df.join(arcs[ups[i - 1]].toDF(f"n{i - 1}", f"n{i}"), f"n{i - 1}")
            lists = neighbour_lists(arcs[ups[-1]]).withColumnRenamed("at", f"n{k - 1}")
            arms[ups] = df.join(lists, f"n{k - 1}").select(*(f"n{i}" for i in range(k)), "ends").repartition("n0")
        return arms[ups]

    for q in queries:
        path, ups = _open_at(q, set(arms))
        one, two = path[k::-1], path[k:]
        df = arm(ups[0]).toDF(*(f"x{v}" for v in one[:-1]), "one").join(arm(ups[1]).toDF(*(f"x{v}" for v in two[:-1]), "two"), f"x{path[k]}")
        bound = [path[k]]
        for v, ends in (*((v, None) for v in (*one[1:-1], *two[1:-1])), (one[-1], "one"), (two[-1], "two")):
            if ends:
                df = df.withColumn(f"x{v}", F.explode(ends)).drop(ends)
            bound.append(v)
            df = _bound_early(df, q, bound, v)
        a, b = (f"x{v}" for v in (path[0], path[-1]))
        found = closed(df.select(*names(s)), a, b, e.edges, sifted).where(condition(q)).select(*canonical_mapping(s, names(s)))
        out = found if out is None else out.unionByName(found)
    return out


def enumerate_cascade(g: DataGraph, s: Pattern, queries: list[MotifQuery] | None = None, count_only: bool = False, share: dict[tuple, DataFrame] | None = None) -> DataFrame:
    """Baseline: for each query, two-way joins one after the other, each with its own shuffle. share: holds, and gets, the joins that queries begin with; they are persisted on disk, and the caller unpersists them. Cycles of five and seven nodes are joined from their middle, so that their paths of three edges aren't shipped."""
    if share is None and s.p in (5, 7) and len(s.edges) == s.p and all(len(s.neighbours(v)) == 2 for v in range(s.p)) and s.connected() and not s.directed:
        return _counted(_odd_cycle_cascade(g, s, queries or cqs_by_orientation(s)), count_only)
    out = None
    for q in queries or cqs_by_orientation(s):
        found = join_query(q, {e: g.edges for e in q.subgoals}, share=share).select(*canonical_mapping(s, names(s)))
        out = found if out is None else out.unionByName(found)
    return _counted(out, count_only)


def enumerate_shared(g: DataGraph, s: Pattern, queries: list[MotifQuery] | None = None, count_only: bool = False) -> DataFrame:
    """All queries by one join tree: the joins are what they have in common, and a mapping stays if any query accepts it."""
    free = MotifQuery(s.p, (), (), tuple((a, b) for a in range(s.p) for b in range(a + 1, s.p)))
    both = g.both_ways().toDF("src", "dst")
    any_of = F.lit(False)
    for q in queries or cqs_by_orientation(s):
        any_of = any_of | condition(q)
    return _counted(_all_mappings(s, free, {e: both for e in s.edges}).where(any_of).select(*canonical_mapping(s, names(s))), count_only)


def bounded_degree(g: DataGraph, s: Pattern, count_only: bool = False) -> DataFrame:
    """A connected pattern grown node by node along adjacency, one join for each further node and a semi-join for each further edge: at most about m * max_degree^(p-2) rows."""
    from motifscan.plans.decompose import elimination_order
    from motifscan.plans.patterns import automorphisms, break_symmetry

    order, less = elimination_order(s), break_symmetry(automorphisms(s))
    both = g.both_ways()
    x = [f"x{i}" for i in range(s.p)]
    df = both.toDF(x[order[0]], x[order[1]])
    bound = [order[0], order[1]]
    df = df.where(pairs_condition([e for e in less if set(e) <= set(bound)], x))
    for v in order[2:]:
        known = [u for u in bound if u in s.neighbours(v)]
        df = df.join(both.toDF(x[known[0]], x[v]), x[known[0]])
        for u in bound:
            df = df.where(F.col(x[u]) != F.col(x[v]))
        bound.append(v)
        df = df.where(pairs_condition([e for e in less if v in e and set(e) <= set(bound)], x))
        for u in known[1:]:
            df = df.join(both.toDF(x[u], x[v]), [x[u], x[v]], "left_semi")
    return _counted(df.select(*x), count_only)


def induced_only(instances: DataFrame, g: DataGraph, s: Pattern) -> DataFrame:
    """Instances whose other pairs of nodes have no edge."""
    both = g.both_ways()
    for a in range(s.p):
        for b in range(a + 1, s.p):
            if (a, b) not in s.edges:
                instances = instances.join(both.toDF(f"x{a}", f"x{b}"), [f"x{a}", f"x{b}"], "left_anti")
    return instances.select(*names(s))


def enumerate_node_labelled(g: DataGraph, s: Pattern, labels: DataFrame, wanted: Sequence[str | None], count_only: bool = False) -> DataFrame:
    """Node labels: pattern node v only takes nodes labelled wanted[v] (null: any). Labels select the nodes before any join; symmetry is what keeps the wanted labels."""
    from motifscan.plans.patterns import automorphisms, break_symmetry

    nodes = {w: labels.where(F.col("label") == w).select("node").distinct() for w in set(wanted) if w is not None}
    both = g.both_ways().toDF("src", "dst")
    of = {}
    for a, b in s.edges:
        rows = both
        for column, w in (("src", wanted[a]), ("dst", wanted[b])):
            if w is not None:
                rows = rows.join(nodes[w].withColumnRenamed("node", column), column, "left_semi")
        of[(a, b)] = rows.select("src", "dst")
    free = MotifQuery(s.p, (), (), tuple((a, b) for a in range(s.p) for b in range(a + 1, s.p)))
    less = break_symmetry(tuple(m for m in automorphisms(s) if all(wanted[m[v]] == wanted[v] for v in range(s.p))))
    return _counted(_all_mappings(s, free, of).where(pairs_condition(less, names(s))).select(*names(s)), count_only)


def enumerate_labelled(g: DataGraph, s: Pattern, count_only: bool = False) -> DataFrame:
    """Edge labels: each subgoal reads its own relation; symmetry is what keeps the labels. Directed patterns too: subgoals keep their direction."""
    if s.directed:
        of = {e: (g.edges.where(F.col("label") == s.label(e)) if s.edge_labels else g.edges).select("src", "dst") for e in s.edges}
    else:
        of = {}
        for e in s.edges:
            rows = g.edges.where(F.col("label") == s.label(e)) if s.edge_labels else g.edges
            of[e] = DataGraph(rows).both_ways().toDF("src", "dst")
    free = MotifQuery(s.p, (), (), tuple((a, b) for a in range(s.p) for b in range(a + 1, s.p)))
    return _counted(_all_mappings(s, free, of).where(is_canonical(s, names(s))).select(*names(s)), count_only)


def anchored(g: DataGraph, s: Pattern, bindings: DataFrame, node: int = 0, most: int = 1_000_000, b: int = 4) -> DataFrame:
    """Mappings whose pattern node `node` is one of the bindings (column node): grown outwards from these, so that the rest of the graph is never read into the joins.

    The bindings' side is broadcast, as it has at most `most` rows; with more, the whole pattern is handed to a one-round scheme of b buckets. Mappings that symmetry makes equal with the anchor fixed count once.
    """
    from motifscan.plans.patterns import automorphisms, break_symmetry

    fixing = tuple(a for a in automorphisms(s) if a[node] == node)
    less = break_symmetry(fixing)
    x = [f"x{i}" for i in range(s.p)]
    start = bindings.select(F.col("node").cast("long").alias(x[node])).distinct()
    if start.limit(most + 1).count() > most:
        return anchored_by_round(g, s, bindings, node, b)
    both = g.both_ways()
    df, bound = start, [node]
    while len(bound) < s.p:
        v = max((v for v in range(s.p) if v not in bound and s.neighbours(v) & set(bound)), key=lambda v: len(s.neighbours(v) & set(bound)))
        known = [u for u in bound if u in s.neighbours(v)]
        step = both.toDF(x[known[0]], x[v])
        df = step.join(F.broadcast(df), x[known[0]]) if len(bound) == 1 else df.join(step, x[known[0]])
        for u in bound:
            df = df.where(F.col(x[u]) != F.col(x[v]))
        bound.append(v)
        df = df.where(pairs_condition([e for e in less if v in e and set(e) <= set(bound)], x))
        for u in known[1:]:
            df = df.join(both.toDF(x[u], x[v]), [x[u], x[v]], "left_semi")
    return df.select(*x)


def co_membership(facts: DataFrame, group: Sequence[str], member: str, size: int, most: int | None = None) -> DataFrame:
    """(group columns, x0 < x1 < ...): all sets of `size` members of one group. Groups of fewer members go first, so that joins only see the others. most: a group of more sets than that stops the job, rather than being cut; null: none does."""
    f = facts.select(*group, F.col(member).cast("long").alias("x")).distinct()
    sizes = f.groupBy(*group).agg(F.count("*").alias("c")).where(F.col("c") >= size)
    if most is not None:
        sets = F.lit(1.0)
        for i in range(size):
            sets = sets * (F.col("c") - i) / (i + 1)
        sizes = sizes.where(F.when(sets <= most, True).otherwise(F.raise_error(F.lit(f"a group has more than {most} sets of {size}")).cast("boolean")))
    f = f.join(sizes.select(*group), list(group), "left_semi")
    df = f.withColumnRenamed("x", "x0")
    for i in range(1, size):
        df = df.join(f.withColumnRenamed("x", f"x{i}"), list(group)).where(F.col(f"x{i - 1}") < F.col(f"x{i}"))
    return df.select(*group, *(f"x{i}" for i in range(size)))


def enumerate_planned(g: DataGraph, s: Pattern, k: int | None = None, edges_per_key: float = 1e6, count_only: bool = False) -> DataFrame:
    """The pattern's instances by the scheme that the planner finds to ship least, from the graph's own size, degrees and, for triangles, ordered two-paths. k: keys; else as many as keep a key's edges below edges_per_key."""
    row = g.stats().first()
    m, degree = row["m"] or 0, row["max_degree"] or 0
    paths = triangles.ordered_two_paths(g).count() if s.p == 3 and len(s.edges) == 3 else None
    scheme = plan(s, k, max(1, m), paths, degree, edges_per_key, row["n"])
    if scheme.note:
        warnings.warn(scheme.note, stacklevel=2)
    if scheme.name == "degree":
        return _counted(triangles.triangles_by_degree(g), count_only)
    if scheme.name == "bounded":
        return bounded_degree(g, s, count_only)
    if scheme.name == "variable":
        return enumerate_variable_oriented(g, s, math.prod(scheme.shares), scheme.shares, cheapest_queries(s, k or math.prod(scheme.shares)), count_only=count_only)
    return enumerate_bucket_oriented(g, s, scheme.b, count_only=count_only)


def enumerate_serial(g: DataGraph, s: Pattern, most: int = 10_000_000, algorithm: str = "grow", count_only: bool = False) -> DataFrame:
    """Baseline: the serial algorithm on the whole graph in one task; for graphs of at most `most` edges, else an error."""
    if g.edges.limit(most + 1).count() > most:
        raise ValueError(f"more than {most} edges for one task")
    return reduce_by_key(g.edges.select(F.lit(0).cast("long").alias("rk"), "src", "dst"), s, algorithm, None, count_only)


def anchored_by_round(g: DataGraph, s: Pattern, bindings: DataFrame, node: int = 0, b: int = 4) -> DataFrame:
    """What `anchored` gives, for many bindings: a one-round scheme on the part of the graph that the anchors reach, a semi-join for each step of the pattern's depth."""
    from motifscan.plans.patterns import automorphisms, break_symmetry

    depth, reached = 0, {node}
    while len(reached) < s.p:
        reached |= {w for v in reached for w in s.neighbours(v)}
        depth += 1
    both, near = g.both_ways(), bindings.select(F.col("node").cast("long").alias("at")).distinct()
    for _ in range(depth):
        near = near.unionByName(both.join(near, "at", "left_semi").select(F.col("to").alias("at"))).distinct()
    part = g.edges.join(near.withColumnRenamed("at", "src"), "src", "left_semi").join(near.withColumnRenamed("at", "dst"), "dst", "left_semi")
    found = enumerate_bucket_oriented(DataGraph(part.select("src", "dst")), s, b)
    group, x = automorphisms(s), names(s)
    images = found.select(F.explode(F.array(*(F.struct(*(F.col(x[a[v]]).alias(x[v]) for v in range(s.p))) for a in group))).alias("i")).select("i.*")
    less = break_symmetry(tuple(a for a in group if a[node] == node))
    return images.where(pairs_condition(less, x)).join(bindings.select(F.col("node").cast("long").alias(x[node])).distinct(), x[node], "left_semi").select(*x)
