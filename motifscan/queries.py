"""The queries of the graph engine, as __spark_entry__.py registers them, and the SQL that gives the same rows."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from motifscan.functions.buckets import canonical_mapping, up_downs
from motifscan.functions.tables import register as register_functions
from motifscan.operators import census, measures, relational, schemes
from motifscan.operators import enumerate as en
from motifscan.operators import triangles as tri
from motifscan.operators.five_cycle import five_cycle_case, five_cycle_join
from motifscan.plans import costs
from motifscan.plans import shares as sh
from motifscan.plans.cqs import acyclic_orientations, cqs_by_orders, cqs_by_orientation, cycle_cq_bound, cycle_cq_count, cycle_cqs, merge_by_orientation
from motifscan.plans.patterns import CATALOGUE, Pattern, automorphisms, break_symmetry
from motifscan.sources import graphs
from motifscan.sources.graphs import DataGraph
from motifscan.sources.tables import load, shared_folder
from motifscan.streaming import edges as streaming

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

#: The graphs in SQL: bodies of a view e(src, dst).
GRAPH_SQL = {
    "copurchase": "WITH f AS (SELECT DISTINCT l_orderkey g, l_partkey v FROM lineitem WHERE l_returnflag = 'R') SELECT DISTINCT a.v src, b.v dst FROM f a JOIN f b ON a.g = b.g AND a.v < b.v",
    "copurchase_bulk": "WITH f AS (SELECT DISTINCT l_orderkey g, l_partkey v FROM lineitem WHERE l_returnflag = 'R' AND l_quantity >= 30) SELECT DISTINCT a.v src, b.v dst FROM f a JOIN f b ON a.g = b.g AND a.v < b.v",
    "cosupply": "WITH f AS (SELECT DISTINCT l_orderkey g, l_suppkey v FROM lineitem WHERE l_quantity >= 45) SELECT DISTINCT a.v src, b.v dst FROM f a JOIN f b ON a.g = b.g AND a.v < b.v",
    "coactive": "WITH f AS (SELECT DISTINCT date_trunc('hour', ts) g, user_id v FROM events WHERE event_type = 'purchase') SELECT DISTINCT a.v src, b.v dst FROM f a JOIN f b ON a.g = b.g AND a.v < b.v",
    "buyer_part": "SELECT DISTINCT least(2 * o_custkey, 2 * l_partkey + 1) src, greatest(2 * o_custkey, 2 * l_partkey + 1) dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_returnflag = 'R' AND l_quantity >= 40",
    "labelled": "WITH f AS (SELECT DISTINCT l_orderkey g, l_returnflag label, l_partkey v FROM lineitem) SELECT DISTINCT a.v src, b.v dst, a.label FROM f a JOIN f b ON a.g = b.g AND a.label = b.label AND a.v < b.v",
    "buys_from": "SELECT DISTINCT o_custkey src, l_suppkey dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "sequence": "WITH a AS (SELECT l_partkey src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey) dst FROM lineitem) SELECT DISTINCT src, dst FROM a WHERE dst IS NOT NULL AND src <> dst",
}
GRAPHS: dict[str, Callable[[SparkSession, str], DataGraph]] = {
    "copurchase": graphs.copurchase_returned,
    "copurchase_bulk": graphs.copurchase_bulk,
    "cosupply": graphs.cosupply_bulk,
    "coactive": graphs.coactive_purchase,
    "buyer_part": graphs.buyer_part,
    "labelled": graphs.labelled_copart,
    "buys_from": graphs.buys_from,
    "sequence": graphs.part_sequence,
}


def register(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def view(graph: str) -> str:
    return f"WITH e AS ({GRAPH_SQL[graph]}), u AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e)"


def pattern_sql(graph: str, s: Pattern, relations: list[str] | None = None) -> str:
    """Plain self-joins of the edges in both directions, each instance by its least mapping."""
    at: dict[int, str] = {}
    where = []
    for n, (a, b) in enumerate(s.edges):
        for v, c in ((a, f"e{n}.src"), (b, f"e{n}.dst")):
            if v in at:
                where.append(f"{at[v]} = {c}")
            else:
                at[v] = c
    where += [f"{at[a]} <> {at[b]}" for a in range(s.p) for b in range(a + 1, s.p) if (a, b) not in s.edges]
    where += [f"{at[a]} < {at[b]}" for a, b in break_symmetry(automorphisms(s))]
    source = ", ".join(f"{relations[n] if relations else 'u'} e{n}" for n in range(len(s.edges)))
    return f"{view(graph)} SELECT {', '.join(f'{at[v]} AS x{v}' for v in range(s.p))} FROM {source} WHERE {' AND '.join(where) or 'TRUE'}"


def on(graph: str, f: Callable[[DataGraph], DataFrame]) -> Query:
    return lambda spark, sf_dir: f(GRAPHS[graph](spark, sf_dir))


def pattern(name: str, graph: str, s: str, f: Callable[[DataGraph, Pattern], DataFrame], oracle: bool = True) -> None:
    register(name, on(graph, lambda g: f(g, CATALOGUE[s])), pattern_sql(graph, CATALOGUE[s]) if oracle else None)


# graphs
for _name, _graph in (("graph_copurchase", "copurchase"), ("graph_copurchase_bulk", "copurchase_bulk"), ("graph_cosupply", "cosupply"), ("graph_coactive", "coactive"), ("graph_buyer_part", "buyer_part"), ("graph_labelled", "labelled"), ("graph_buys_from", "buys_from"), ("graph_sequence", "sequence")):
    register(_name, on(_graph, lambda g: g.edges), GRAPH_SQL[_graph])

register(
    "graph_stats",
    lambda spark, sf: GRAPHS["copurchase"](spark, sf).stats().select(F.lit("copurchase").alias("graph"), "*").unionByName(GRAPHS["cosupply"](spark, sf).stats().select(F.lit("cosupply").alias("graph"), "*")).unionByName(GRAPHS["buyer_part"](spark, sf).stats().select(F.lit("buyer_part").alias("graph"), "*")),
    " UNION ALL ".join(f"SELECT * FROM ({view(g)}, d AS (SELECT src v, count(*) c FROM u GROUP BY 1) SELECT '{g}' AS graph, count(*) AS n, CAST(sum(c) / 2 AS BIGINT) AS m, max(c) AS max_degree FROM d)" for g in ("copurchase", "cosupply", "buyer_part")),
)
_DEGREES = ", d AS (SELECT src v, count(*) c FROM u GROUP BY 1), o AS (SELECT CASE WHEN (a.c, e.src) < (b.c, e.dst) THEN e.src ELSE e.dst END lo, CASE WHEN (a.c, e.src) < (b.c, e.dst) THEN e.dst ELSE e.src END hi, least(a.c, b.c) lo_degree, greatest(a.c, b.c) hi_degree FROM e JOIN d a ON a.v = e.src JOIN d b ON b.v = e.dst)"
register("degree_order_edges", on("copurchase", tri.degree_ordered), view("copurchase") + _DEGREES + " SELECT * FROM o")
register("two_paths_ordered", on("copurchase", tri.ordered_two_paths), view("copurchase") + _DEGREES + " SELECT a.lo AS v, a.hi AS u, b.hi AS w FROM o a JOIN o b ON a.lo = b.lo AND a.hi < b.hi")
register("degree_split", on("copurchase", tri.degree_split), view("copurchase") + ", d AS (SELECT src v, count(*) c FROM u GROUP BY 1) SELECT v AS node, c AS degree, c >= sqrt((SELECT count(*) FROM e)) AS high FROM d")

# triangles
for _name, _f in {
    "tri_multiway": lambda g: tri.triangles_multiway(g, 4),
    "tri_multiway_dedup": lambda g: tri.triangles_multiway(g, 4, True),
    "tri_ordered": lambda g: tri.triangles_ordered(g, 4),
    "tri_nodeset_owner": lambda g: tri.triangles_nodeset(g, 5),
    "tri_nodeset_distinct": lambda g: tri.triangles_nodeset(g, 5, "distinct"),
    "tri_by_degree": tri.triangles_by_degree,
    "tri_cascade": tri.triangles_cascade,
}.items():
    register(_name, on("copurchase", _f), pattern_sql("copurchase", CATALOGUE["triangle"]))
register("tri_cosupply_ordered", on("cosupply", lambda g: tri.triangles_ordered(g, 6)), pattern_sql("cosupply", CATALOGUE["triangle"]))
register("tri_bipartite_none", on("buyer_part", lambda g: tri.triangles_ordered(g, 4)), pattern_sql("buyer_part", CATALOGUE["triangle"]))
register("tri_undirected_sixfold", on("copurchase", tri.triangles_undirected), view("copurchase") + " SELECT a.src AS x0, a.dst AS x1, b.dst AS x2 FROM u a JOIN u b ON a.dst = b.src JOIN u c ON c.src = a.src AND c.dst = b.dst")
register(
    "tri_nodeset_multiplicity",
    on("copurchase", lambda g: tri.nodeset_multiplicity(g, 5)),
    f"WITH t AS ({pattern_sql('copurchase', CATALOGUE['triangle'])}), k AS (SELECT len(list_distinct([x0 % 5, x1 % 5, x2 % 5])) g FROM t) SELECT g AS n_groups, count(*) AS instances, count(*) * CASE g WHEN 1 THEN 6 WHEN 2 THEN 3 ELSE 1 END AS found, count(*) * CASE g WHEN 1 THEN 6 WHEN 2 THEN 3 ELSE 1 END AS formula FROM k GROUP BY g",
)

# patterns by scheme
pattern("square_bucket", "copurchase", "square", lambda g, s: en.enumerate_bucket_oriented(g, s, 4))
pattern("square_bucket_joins", "copurchase", "square", lambda g, s: en.enumerate_bucket_joins(g, s, 3))
pattern("square_variable", "copurchase", "square", lambda g, s: en.enumerate_variable_oriented(g, s, 32))
pattern("square_cq", "copurchase", "square", lambda g, s: en.enumerate_cq_oriented(g, s, 32))
pattern("square_orders", "copurchase", "square", lambda g, s: en.enumerate_variable_oriented(g, s, 32, queries=cqs_by_orders(s)))
pattern("square_undirected", "copurchase", "square", lambda g, s: en.enumerate_undirected(g, s, 16))
pattern("square_nodeset", "copurchase", "square", lambda g, s: en.enumerate_nodeset(g, s, 6))
pattern("square_cascade", "copurchase", "square", en.enumerate_cascade)
pattern("square_shared", "copurchase", "square", en.enumerate_shared)
pattern("square_decomposed", "copurchase", "square", lambda g, s: en.enumerate_bucket_oriented(g, s, 4, algorithm="combine"))
pattern("square_buyer_part", "buyer_part", "square", lambda g, s: en.enumerate_bucket_oriented(g, s, 4))
pattern("pendant_bucket", "copurchase", "pendant_triangle", lambda g, s: en.enumerate_bucket_oriented(g, s, 4))
pattern("pendant_variable", "copurchase", "pendant_triangle", lambda g, s: en.enumerate_variable_oriented(g, s, 60))
pattern("pendant_merged", "copurchase", "pendant_triangle", lambda g, s: en.enumerate_cascade(g, s, merge_by_orientation(s)))
pattern("diamond_bucket", "copurchase", "diamond", lambda g, s: en.enumerate_bucket_oriented(g, s, 4))
pattern("k4_bucket", "copurchase", "k4", lambda g, s: en.enumerate_bucket_oriented(g, s, 4))
pattern("k4_cosupply_joins", "cosupply", "k4", lambda g, s: en.enumerate_bucket_joins(g, s, 3))
pattern("k5_bucket", "copurchase", "k5", lambda g, s: en.enumerate_bucket_oriented(g, s, 3))
pattern("pentagon_cycle_cqs", "copurchase", "pentagon", lambda g, s: en.enumerate_bucket_oriented(g, s, 3, queries=cycle_cqs(5)))
pattern("pentagon_cycle_cascade", "copurchase", "pentagon", lambda g, s: en.enumerate_cascade(g, s, cycle_cqs(5)))
pattern("pentagon_odd_cycle", "copurchase", "pentagon", lambda g, s: en.enumerate_bucket_oriented(g, s, 3, algorithm="odd"))
pattern("hexagon_cycle_cqs", "buyer_part", "hexagon", lambda g, s: en.enumerate_bucket_oriented(g, s, 2, queries=cycle_cqs(6)))
pattern("hexagon_cycle_cascade", "buyer_part", "hexagon", lambda g, s: en.enumerate_cascade(g, s, cycle_cqs(6)))
pattern("hexagon_variable", "buyer_part", "hexagon", lambda g, s: en.enumerate_variable_oriented(g, s, 32, shares=[1, 2, 2, 2, 2, 2]))
pattern("heptagon_odd_cycle", "copurchase_bulk", "heptagon", lambda g, s: en.enumerate_bucket_oriented(g, s, 2, algorithm="odd"))
pattern("heptagon_cycle_cqs", "copurchase_bulk", "heptagon", lambda g, s: en.enumerate_bucket_oriented(g, s, 2, queries=cycle_cqs(7)))
pattern("heptagon_bipartite_none", "buyer_part", "heptagon", lambda g, s: en.enumerate_bucket_oriented(g, s, 2, algorithm="odd"))
register("heptagon_odd_joins", on("copurchase_bulk", lambda g: tri.odd_cycles(g, 7).select(*canonical_mapping(CATALOGUE["heptagon"], [f"x{i}" for i in range(7)]))), pattern_sql("copurchase_bulk", CATALOGUE["heptagon"]))
register("pentagon_odd_joins", on("copurchase", lambda g: tri.odd_cycles(g, 5).select(*canonical_mapping(CATALOGUE["pentagon"], [f"x{i}" for i in range(5)]))), pattern_sql("copurchase", CATALOGUE["pentagon"]))
pattern("square_planned", "copurchase", "square", lambda g, s: en.enumerate_planned(g, s, 100))
pattern("triangle_planned", "copurchase", "triangle", lambda g, s: en.enumerate_planned(g, s, 220))
pattern("pendant_orders", "copurchase", "pendant_triangle", lambda g, s: en.enumerate_bucket_oriented(g, s, 3, queries=merge_by_orientation(s)))
pattern("square_serial", "copurchase", "square", en.enumerate_serial)
pattern("square_shared_joins", "copurchase", "square", lambda g, s: en.enumerate_cascade(g, s, cqs_by_orders(s), share={}))
pattern("star4_decomposed", "buyer_part", "star4", lambda g, s: en.enumerate_bucket_oriented(g, s, 3, algorithm="combine"))
pattern("hexagon_copurchase_bulk", "copurchase_bulk", "hexagon", lambda g, s: en.enumerate_bucket_oriented(g, s, 2))
pattern("cube_bucket", "copurchase", "cube", lambda g, s: en.enumerate_bucket_oriented(g, s, 2))
pattern("k33_bucket", "copurchase", "k33", lambda g, s: en.enumerate_bucket_oriented(g, s, 2))


def _count(name: str, graph: str, s: str, f: Callable[[DataGraph, Pattern], DataFrame]) -> None:
    """A method that counts without listing; the number as SQL finds it."""
    register(name, on(graph, lambda g: f(g, CATALOGUE[s])), f"SELECT count(*) AS n FROM ({pattern_sql(graph, CATALOGUE[s])})")


_count("square_bucket_count", "copurchase", "square", lambda g, s: en.enumerate_bucket_oriented(g, s, 4, count_only=True))
_count("square_variable_count", "copurchase", "square", lambda g, s: en.enumerate_variable_oriented(g, s, 32, count_only=True))
_count("square_nodeset_weight", "copurchase", "square", lambda g, s: en.enumerate_nodeset(g, s, 5, "weight", count_only=True))
register("tri_nodeset_weight", on("copurchase", lambda g: tri.triangles_nodeset(g, 5, "weight").agg(F.round(F.sum("weight")).cast("long").alias("n"))), f"SELECT count(*) AS n FROM ({pattern_sql('copurchase', CATALOGUE['triangle'])})")
_LETTERS = lambda turn: " || ".join(f"CASE WHEN x{a} < x{b} THEN 'u' ELSE 'd' END" for a, b in zip(turn, turn[1:] + turn[:1], strict=True))
register(
    "pentagon_runs",
    on("copurchase", lambda g: en.enumerate_bucket_oriented(g, CATALOGUE["pentagon"], 3).groupBy(up_downs([f"x{i}" for i in range(5)]).alias("up_downs")).agg(F.count("*").alias("n"))),
    f"SELECT greatest({_LETTERS([0, 1, 2, 3, 4])}, {_LETTERS([0, 4, 3, 2, 1])}) AS up_downs, count(*) AS n FROM ({pattern_sql('copurchase', CATALOGUE['pentagon'])}) GROUP BY 1",
)
pattern("house_decomposed", "copurchase", "house", lambda g, s: en.enumerate_bucket_oriented(g, s, 3, algorithm="combine"))
pattern("bowtie_decomposed", "copurchase", "bowtie", lambda g, s: en.enumerate_bucket_oriented(g, s, 3, algorithm="combine"))
pattern("prism_decomposed", "copurchase", "prism", lambda g, s: en.enumerate_bucket_oriented(g, s, 2, algorithm="combine"))
pattern("gem_hamilton", "copurchase", "gem", lambda g, s: en.enumerate_bucket_oriented(g, s, 3, algorithm="odd"))
pattern("k4_bounded", "copurchase", "k4", en.bounded_degree)
pattern("diamond_bounded", "copurchase", "diamond", en.bounded_degree)
pattern("path4_bounded", "buyer_part", "path4", en.bounded_degree)
pattern("star4_bounded", "buyer_part", "star4", en.bounded_degree)
pattern("path3_decomposed", "buyer_part", "path3", lambda g, s: en.enumerate_bucket_oriented(g, s, 3, algorithm="combine"))
register("square_induced", on("copurchase", lambda g: en.induced_only(en.bounded_degree(g, CATALOGUE["square"]), g, CATALOGUE["square"])), pattern_sql("copurchase", CATALOGUE["square"]) + " AND NOT EXISTS (SELECT 1 FROM u c WHERE c.src = e0.src AND c.dst = e1.dst) AND NOT EXISTS (SELECT 1 FROM u c WHERE c.src = e0.dst AND c.dst = e2.dst)")
register("square_all_mappings", on("copurchase", lambda g: en.enumerate_all_mappings(g, CATALOGUE["square"]).agg(F.count("*").alias("n"), (F.count("*") / len(automorphisms(CATALOGUE["square"]))).cast("long").alias("instances"))), f"SELECT 8 * count(*) AS n, count(*) AS instances FROM ({pattern_sql('copurchase', CATALOGUE['square'])})")

# labels, directions, anchors, common membership
_LABELLED = Pattern(3, ((0, 1), (1, 2), (0, 2)), edge_labels=("A", "N", "R"), name="labelled_triangle")
register(
    "labelled_triangle",
    on("labelled", lambda g: en.enumerate_labelled(g, _LABELLED)),
    f"WITH e AS MATERIALIZED ({GRAPH_SQL['labelled']}), u AS MATERIALIZED (SELECT src, dst, label FROM e UNION ALL SELECT dst, src, label FROM e), a AS MATERIALIZED (SELECT src, dst FROM u WHERE label = 'A'), n AS MATERIALIZED (SELECT src, dst FROM u WHERE label = 'N'), r AS MATERIALIZED (SELECT src, dst FROM u WHERE label = 'R'), p AS MATERIALIZED (SELECT r.src x0, a.dst x1, r.dst x2 FROM r JOIN a ON a.src = r.src WHERE a.dst <> r.dst) SELECT p.x0, p.x1, p.x2 FROM p JOIN n ON n.src = p.x1 AND n.dst = p.x2",
)


def _node_labelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("node"), F.substring("p_brand", 1, 7).alias("label"))
    return en.enumerate_node_labelled(GRAPHS["copurchase"](spark, sf_dir), CATALOGUE["square"], labels, ["Brand#1", None, "Brand#1", None])


register(
    "node_labelled_square",
    _node_labelled,
    f"{view('copurchase')}, l AS (SELECT p_partkey v FROM part WHERE substring(p_brand, 1, 7) = 'Brand#1') SELECT a.src AS x0, a.dst AS x1, b.dst AS x2, c.dst AS x3 FROM u a JOIN u b ON a.dst = b.src JOIN u c ON c.src = b.dst JOIN u d ON d.src = c.dst AND d.dst = a.src WHERE a.src < b.dst AND a.dst < c.dst AND a.src IN (SELECT v FROM l) AND b.dst IN (SELECT v FROM l)",
)
_DIRECTED = Pattern(3, ((0, 1), (1, 2), (2, 0)), directed=True, name="directed_cycle3")
register("directed_cycle3", on("sequence", lambda g: en.enumerate_labelled(g, _DIRECTED)), f"WITH e AS ({GRAPH_SQL['sequence']}) SELECT a.src AS x0, b.src AS x1, c.src AS x2 FROM e a JOIN e b ON a.dst = b.src JOIN e c ON b.dst = c.src AND c.dst = a.src WHERE a.src < b.src AND a.src < c.src AND b.src <> c.src")


def _anchored_square(spark: SparkSession, sf_dir: str) -> DataFrame:
    dearest = load(spark, sf_dir, "part").agg(F.max("p_retailprice").alias("top"))
    nodes = load(spark, sf_dir, "part").join(F.broadcast(dearest), F.col("p_retailprice") == F.col("top")).select(F.col("p_partkey").alias("node"))
    return en.anchored(GRAPHS["copurchase"](spark, sf_dir), CATALOGUE["square"], nodes)


register("anchored_square", _anchored_square, view("copurchase") + " SELECT a.src AS x0, a.dst AS x1, b.dst AS x2, d.dst AS x3 FROM u a JOIN u b ON a.dst = b.src JOIN u d ON d.src = a.src JOIN u c ON c.src = b.dst AND c.dst = d.dst WHERE a.src IN (SELECT p_partkey FROM part WHERE p_retailprice = (SELECT max(p_retailprice) FROM part)) AND a.src <> b.dst AND a.dst < d.dst")


def _five_buyers(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = load(spark, sf_dir, "lineitem").where("l_returnflag = 'R'").select("l_orderkey", "l_partkey", "l_suppkey")
    facts = items.join(load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate"), F.col("o_orderkey") == F.col("l_orderkey"))
    facts = facts.join(load(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey"), F.col("s_suppkey") == F.col("l_suppkey")).join(load(spark, sf_dir, "part").select("p_partkey", "p_brand"), F.col("p_partkey") == F.col("l_partkey"))
    facts = facts.select("p_brand", "s_nationkey", F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), "o_custkey")
    return en.co_membership(facts, ["p_brand", "s_nationkey", "y", "q"], "o_custkey", 5)


register(
    "co_membership_five",
    _five_buyers,
    "WITH f AS (SELECT DISTINCT p_brand, s_nationkey, CAST(year(o_orderdate) AS INT) y, CAST(quarter(o_orderdate) AS INT) q, o_custkey c FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN supplier ON s_suppkey = l_suppkey JOIN part ON p_partkey = l_partkey WHERE l_returnflag = 'R') SELECT a.p_brand, a.s_nationkey, a.y, a.q, a.c AS x0, b.c AS x1, c.c AS x2, d.c AS x3, e.c AS x4 FROM f a JOIN f b USING (p_brand, s_nationkey, y, q) JOIN f c USING (p_brand, s_nationkey, y, q) JOIN f d USING (p_brand, s_nationkey, y, q) JOIN f e USING (p_brand, s_nationkey, y, q) WHERE a.c < b.c AND b.c < c.c AND c.c < d.c AND d.c < e.c",
)

# five relations
_FIVE = "WITH r1 AS (SELECT DISTINCT CAST(c_nationkey AS BIGINT) a, c_custkey b FROM customer), r2 AS (SELECT DISTINCT o_custkey a, o_orderkey b FROM orders), r3 AS (SELECT DISTINCT l_orderkey a, l_partkey b FROM lineitem), r4 AS (SELECT DISTINCT l_partkey a, l_suppkey b FROM lineitem), r5 AS (SELECT DISTINCT s_suppkey a, CAST(s_nationkey AS BIGINT) b FROM supplier)"
_FIVE_JOIN = "SELECT r1.a AS v1, r1.b AS v2, r2.b AS v3, r3.b AS v4, r4.b AS v5 FROM r1 JOIN r2 ON r1.b = r2.a JOIN r3 ON r2.b = r3.a JOIN r4 ON r3.b = r4.a JOIN r5 ON r4.b = r5.a AND r5.b = r1.a"
register("five_cycle_case_a", lambda spark, sf: five_cycle_join(graphs.five_relations(spark, sf), "A"), f"{_FIVE} {_FIVE_JOIN}")


_GROUPS = "g1 AS (SELECT DISTINCT CAST(n_regionkey AS BIGINT) a, CAST(n_nationkey AS BIGINT) b FROM nation), sold AS MATERIALIZED (SELECT CAST(c_nationkey AS BIGINT) n, l_partkey p, l_suppkey s FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey), g2 AS MATERIALIZED (SELECT DISTINCT n, p FROM sold), g3 AS MATERIALIZED (SELECT DISTINCT l_partkey p, l_suppkey s FROM lineitem), g4 AS MATERIALIZED (SELECT DISTINCT s, n FROM sold)"


def _case_b(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole relations of very unequal sizes, counted, not given."""
    return five_cycle_join(graphs.group_relations(spark, sf_dir), by=["v1", "v2", "v5"])


register(
    "five_cycle_case_b",
    _case_b,
    f"WITH {_GROUPS} SELECT x.a AS v1, x.b AS v2, y.b AS v5, count(*) AS n FROM g1 x JOIN g1 y ON x.a = y.a JOIN g2 ON g2.n = x.b JOIN g3 ON g3.p = g2.p JOIN g4 ON g4.s = g3.s AND g4.n = y.b GROUP BY ALL",
)
register(
    "five_cycle_cases",
    lambda spark, sf: spark.createDataFrame([(name, *five_cycle_case([r.count() for r in rels])[:2]) for name, rels in (("orders", graphs.five_relations(spark, sf)), ("regions", graphs.group_relations(spark, sf)))], "relations string, case string, rotation long"),
    f"{_FIVE}, {_GROUPS}, z AS (SELECT 'orders' relations, [(SELECT count(*) FROM r1), (SELECT count(*) FROM r2), (SELECT count(*) FROM r3), (SELECT count(*) FROM r4), (SELECT count(*) FROM r5)] n UNION ALL SELECT 'regions', [(SELECT count(*) FROM g1), (SELECT count(*) FROM g2), (SELECT count(*) FROM g3), (SELECT count(*) FROM g4), (SELECT count(*) FROM g1)]), t AS (SELECT relations, sqrt(list_product(list_transform(n, lambda x: CAST(x AS DOUBLE)))) root, list_transform(range(5), lambda r: CAST(n[r + 1] AS DOUBLE) * n[(r + 4) % 5 + 1] * n[(r + 2) % 5 + 1]) three FROM z) SELECT relations, CASE WHEN list_min(three) < root THEN 'B' ELSE 'A' END AS \"case\", CAST(list_position(three, list_min(three)) - 1 AS BIGINT) AS rotation FROM t",
)

# measures
_BUCKETS = {"ordered": 5, "multiway": 4, "multiway_dedup": 4, "nodeset": 6}


def _scheme_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    g, out = GRAPHS["copurchase"](spark, sf_dir), None
    for scheme, b in _BUCKETS.items():
        row = measures.cost_rows(g, scheme, b, 3, "mod")
        out = row if out is None else out.unionByName(row)
    return out


def _keys_sql(scheme: str, b: int, p: int = 3) -> str:
    """Rows k of each edge and key."""
    w = f"range({b}) w(w)"
    if scheme == "ordered":
        return f"SELECT list_sort([src % {b}, dst % {b}, w.w]) k FROM e, {w}"
    if scheme.startswith("multiway"):
        union = "UNION" if scheme.endswith("dedup") else "UNION ALL"
        return f"SELECT k FROM (SELECT src, dst, [src % {b}, dst % {b}, w.w] k FROM e, {w} {union} SELECT src, dst, [w.w, src % {b}, dst % {b}] FROM e, {w} {union} SELECT src, dst, [src % {b}, w.w, dst % {b}] FROM e, {w})"
    lists = ", ".join(f"range({b}) t{i}(x{i})" for i in range(p))
    chain = " AND ".join(f"x{i} < x{i + 1}" for i in range(p - 1))
    members = ", ".join(f"x{i}" for i in range(p))
    return f"SELECT s.k FROM e, (SELECT [{members}] k FROM {lists} WHERE {chain}) s WHERE list_contains(s.k, src % {b}) AND list_contains(s.k, dst % {b})"


def _cost_sql(scheme: str, b: int, p: int = 3, body: str | None = None) -> str:
    return f"SELECT '{scheme}' AS scheme, CAST({b} AS BIGINT) AS b, CAST(sum(c) AS BIGINT) AS pairs, count(*) AS keys_hit, max(c) AS max_load FROM (SELECT k, count(*) c FROM ({body or _keys_sql(scheme, b, p)}) GROUP BY k)"


register("cost_tri_schemes", _scheme_costs, f"WITH e AS ({GRAPH_SQL['copurchase']}) " + " UNION ALL ".join(_cost_sql(s, b) for s, b in _BUCKETS.items()))
_TWO = "(SELECT [a.a, b.b] r FROM range(5) a(a), range(5) b(b) WHERE a.a <= b.b)"
register("cost_bucket_p4", on("copurchase", lambda g: measures.cost_rows(g, "bucket", 5, 4, "mod")), f"WITH e AS ({GRAPH_SQL['copurchase']}) " + _cost_sql("bucket", 5, 4, f"SELECT list_sort(list_concat([src % 5, dst % 5], s.r)) k FROM e, {_TWO} s"))
register("cost_nodeset_p4", on("copurchase", lambda g: measures.cost_rows(g, "nodeset", 6, 4, "mod")), f"WITH e AS ({GRAPH_SQL['copurchase']}) " + _cost_sql("nodeset", 6, 4))
_LOAD = f"WITH e AS ({GRAPH_SQL['copurchase']}), s AS (SELECT DISTINCT list_sort([src % 4, dst % 4, w.w]) k, src, dst FROM e, range(4) w(w))"
register(
    "load_per_key",
    on("copurchase", lambda g: measures.load_per_key(measures.shipped(g, "ordered", 4, 3, "mod"))),
    f"{_LOAD} SELECT CAST(k[1] + k[2] * (k[2] + 1) // 2 + k[3] * (k[3] + 1) * (k[3] + 2) // 6 AS BIGINT) AS rk, count(*) AS edges, (SELECT count(DISTINCT v) FROM (SELECT src v, k kk FROM s UNION ALL SELECT dst, k FROM s) WHERE kk = k) AS nodes FROM s GROUP BY k",
)
register("found_once", on("copurchase", lambda g: measures.discoveries(tri.triangles_nodeset(g, 5, "none", "mod"))), f"WITH t AS ({pattern_sql('copurchase', CATALOGUE['triangle'])}), k AS (SELECT CASE len(list_distinct([x0 % 5, x1 % 5, x2 % 5])) WHEN 1 THEN 6 WHEN 2 THEN 3 ELSE 1 END AS times FROM t) SELECT CAST(times AS BIGINT) AS times, count(*) AS instances FROM k GROUP BY 1")
register("complete", on("copurchase", lambda g: measures.completeness(tri.triangles_ordered(g, 5), tri.triangles_cascade(g))), f"SELECT count(*) AS expected, CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS extra FROM ({pattern_sql('copurchase', CATALOGUE['triangle'])})")
_SWEEP = [(scheme, b, 3) for scheme in ("ordered", "multiway_dedup", "nodeset") for b in (3, 4, 6, 8, 10, 12)]
_SWEEP_P = [(scheme, b, p) for p in (3, 4, 5) for scheme in ("bucket", "nodeset") for b in (4, 6, 8) if b >= p]


def _sweep_sql(points: list[tuple[str, int, int]]) -> str:
    def body(scheme: str, b: int, p: int) -> str | None:
        if scheme != "bucket":
            return None
        lists = ", ".join(f"range({b}) t{i}(x{i})" for i in range(p - 2))
        chain = " AND ".join(f"x{i} <= x{i + 1}" for i in range(p - 3)) or "TRUE"
        return f"SELECT list_sort(list_concat([src % {b}, dst % {b}], s.r)) k FROM e, (SELECT [{', '.join(f'x{i}' for i in range(p - 2))}] r FROM {lists} WHERE {chain}) s"

    return f"WITH e AS MATERIALIZED ({GRAPH_SQL['copurchase']}) " + " UNION ALL ".join(f"SELECT *, CAST({p} AS BIGINT) AS p FROM ({_cost_sql(s, b, p, body(s, b, p))})" for s, b, p in points)


register("sweep_tri_schemes", on("copurchase", lambda g: measures.sweep(g, _SWEEP, "mod")), _sweep_sql(_SWEEP))
register("sweep_bucket_nodeset", on("copurchase", lambda g: measures.sweep(g, _SWEEP_P, "mod")), _sweep_sql(_SWEEP_P))
_AT_220 = [("nodeset", 12, 3), ("multiway_dedup", 6, 3), ("ordered", 10, 3)]
register("schemes_at_equal_keys", on("copurchase", lambda g: measures.sweep(g, _AT_220, "mod")), _sweep_sql(_AT_220))


def _square_shares(g: DataGraph) -> DataFrame:
    s, out = CATALOGUE["square"], None
    for k in (8, 32, 128):
        row = measures.share_pairs(g, s, k, cqs_by_orientation(s, "bidirectional"))
        out = row if out is None else out.unionByName(row)
    return out


register("sweep_square_shares", on("copurchase", _square_shares), f"WITH e AS MATERIALIZED ({GRAPH_SQL['copurchase']}) SELECT CAST(t.k AS BIGINT) AS k, CAST(round((SELECT count(*) FROM e) * 4 * sqrt(2 * t.k)) AS BIGINT) AS pairs FROM (VALUES (8), (32), (128)) t(k)")


def _single_pairs(k: int) -> int:
    """What the square's queries ship for an edge if each has its own job."""
    s, total = CATALOGUE["square"], 0.0
    for q in cqs_by_orientation(s):
        ts = sh.terms(s, [q])
        total += sh.cost(s.p, ts, [float(x) for x in sh.round_shares(s.p, ts, sh.optimise(s.p, ts, k), k)])
    return round(total)


register(
    "joint_or_separate",
    on("copurchase", lambda g: measures.grouping_pairs(g, CATALOGUE["square"], 32, cqs_by_orientation(CATALOGUE["square"], "bidirectional"))),
    f"WITH e AS MATERIALIZED ({GRAPH_SQL['copurchase']}) SELECT 'joint' AS evaluation, CAST(1 AS BIGINT) AS jobs, 32 * count(*) AS pairs FROM e UNION ALL SELECT 'separate', 3, {_single_pairs(32)} * count(*) FROM e",
)
register(
    "shipped_by_plan",
    on("copurchase", lambda g: measures.shipped_by_plan(g, 10)),
    view("copurchase") + _DEGREES + " SELECT 'cascade' AS plan, CAST(3 * (SELECT count(*) FROM e) + (SELECT count(*) FROM e a JOIN e b ON a.dst = b.src) AS BIGINT) AS rows UNION ALL SELECT 'degree', CAST(3 * (SELECT count(*) FROM e) + (SELECT count(*) FROM o a JOIN o b ON a.lo = b.lo AND a.hi < b.hi) AS BIGINT) UNION ALL SELECT 'one_round', CAST(10 * (SELECT count(*) FROM e) AS BIGINT)",
)
register(
    "load_summary",
    on("copurchase", lambda g: measures.load_summary(measures.shipped(g, "ordered", 10, 3, "mod"))),
    f"WITH e AS ({GRAPH_SQL['copurchase']}), l AS (SELECT k, count(*) c FROM ({_keys_sql('ordered', 10)}) GROUP BY k) SELECT count(*) AS keys, avg(c) AS mean, quantile_cont(c, 0.5) AS p50, quantile_cont(c, 0.99) AS p99, max(c) AS max, max(c) / avg(c) AS skew FROM l",
)
# the triangle kernel looks at each ordered two-path twice: as it makes it and as it looks for the closing edge. Degrees are those within the key
_PROBES = lambda b: f"SELECT CAST({b} AS BIGINT) AS b, CAST(2 * sum(c * (c - 1) / 2) AS BIGINT) AS probes FROM (WITH s AS MATERIALIZED (SELECT DISTINCT list_sort([src % {b}, dst % {b}, w.w]) k, src, dst FROM e, range({b}) w(w)), d AS MATERIALIZED (SELECT k, v, count(*) c FROM (SELECT k, src v FROM s UNION ALL SELECT k, dst FROM s) GROUP BY k, v), o AS (SELECT s.k, CASE WHEN (x.c, s.src) < (y.c, s.dst) THEN s.src ELSE s.dst END lo FROM s JOIN d x ON x.k = s.k AND x.v = s.src JOIN d y ON y.k = s.k AND y.v = s.dst) SELECT k, lo, count(*) c FROM o GROUP BY k, lo)"
register("convertible_probes", on("copurchase", lambda g: measures.convertible_work(g, CATALOGUE["triangle"], (1, 2, 4, 8), "odd", "mod")), f"WITH e AS MATERIALIZED ({GRAPH_SQL['copurchase']}) " + " UNION ALL ".join(_PROBES(b) for b in (1, 2, 4, 8)))


def _sql_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triangles by the table function at each key of the bucket-list scheme, kept by their owners."""
    register_functions(spark)
    view = f"shipped_{uuid.uuid4().hex}"
    schemes.multiset_keys(GRAPHS["copurchase"](spark, sf_dir).edges, 4, 3).createOrReplaceTempView(view)
    found = spark.sql(f"SELECT rk, nodes[0] AS x0, nodes[1] AS x1, nodes[2] AS x2 FROM motif_instances(TABLE(SELECT rk, src, dst FROM {view}) PARTITION BY (rk), 'triangle')")
    return found.where(schemes.multiset_owner(["x0", "x1", "x2"], 4) == F.col("rk")).drop("rk")


register("tri_table_function", _sql_functions, pattern_sql("copurchase", CATALOGUE["triangle"]))


def _triangles_by_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_functions(spark)
    return GRAPHS["labelled"](spark, sf_dir).edges.groupBy("label").agg(F.expr("triangle_count(src, dst)").alias("triangles"))


register("triangle_count_by_label", _triangles_by_label, f"WITH e AS ({GRAPH_SQL['labelled']}) SELECT a.label, count(*) AS triangles FROM e a JOIN e b ON a.dst = b.src AND a.label = b.label JOIN e c ON c.src = a.src AND c.dst = b.dst AND c.label = a.label GROUP BY a.label")


# what the plans decide, and what that comes to over the edges of a given graph
def _over_edges(spark: SparkSession, sf_dir: str, rows: list[tuple], schema: str) -> DataFrame:
    """The rows of a plan, each with the graph's number of edges, m."""
    return spark.createDataFrame(rows, schema).crossJoin(GRAPHS["copurchase"](spark, sf_dir).edges.agg(F.count("*").alias("m")))


_OVER_EDGES = f"WITH e AS ({GRAPH_SQL['copurchase']}), z AS (SELECT count(*) m FROM e)"


def _cq_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries of each pattern, and the rows that the classes' subgoals read of the graph."""
    rows = [(n, len(cqs_by_orders(s)), len(acyclic_orientations(s)), len(cqs_by_orientation(s)), len(automorphisms(s)), len(s.edges)) for n in ("triangle", "square", "pendant_triangle", "diamond", "k4", "path3", "path4", "star4", "star5", "pentagon", "house", "bowtie") for s in (CATALOGUE[n],)]
    plans = _over_edges(spark, sf_dir, rows, "pattern string, orders long, orientations long, classes long, symmetries long, subgoals long")
    return plans.select("pattern", "orders", "orientations", "classes", "symmetries", (F.col("classes") * F.col("subgoals") * F.col("m")).alias("reads"))


register("cq_counts", _cq_counts, f"{_OVER_EDGES} SELECT pattern, CAST(orders AS BIGINT) AS orders, CAST(orientations AS BIGINT) AS orientations, CAST(classes AS BIGINT) AS classes, CAST(symmetries AS BIGINT) AS symmetries, CAST(classes * subgoals * m AS BIGINT) AS reads FROM z, (VALUES ('triangle',1,6,1,6,3),('square',3,14,3,8,4),('pendant_triangle',12,12,6,2,4),('diamond',6,18,6,4,5),('k4',1,24,1,24,6),('path3',3,4,3,2,2),('path4',12,8,4,2,3),('star4',4,8,4,6,3),('star5',5,16,5,24,4),('pentagon',12,30,3,10,5),('house',60,42,21,2,6),('bowtie',15,36,6,8,6)) t(pattern, orders, orientations, classes, symmetries, subgoals)")

def _cycle_cq_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries of cycles, the bound on their number, and the rows that their subgoals read of the graph."""
    plans = _over_edges(spark, sf_dir, [(p, cycle_cq_count(p), cycle_cq_bound(p)) for p in range(3, 13)], "p long, queries long, bound double")
    return plans.select("p", "queries", "bound", (F.col("queries") * F.col("p") * F.col("m")).alias("reads"))


register("cycle_cq_counts", _cycle_cq_counts, f"{_OVER_EDGES} SELECT CAST(p AS BIGINT) AS p, CAST(q AS BIGINT) AS queries, (power(2, p) - 2) / (2 * p) AS bound, CAST(q * p * m AS BIGINT) AS reads FROM z, (VALUES (3,1),(4,3),(5,3),(6,8),(7,9),(8,21),(9,29),(10,61),(11,93),(12,191)) t(p, q)")


def _share_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    pendant = tuple(sh.Term(a, b) for a, b in CATALOGUE["pendant_triangle"].edges)
    square = sh.terms(CATALOGUE["square"], cqs_by_orientation(CATALOGUE["square"]))
    hexagon = tuple(sh.Term(a, b, 1.0 if 0 in (a, b) else 2.0) for a, b in CATALOGUE["hexagon"].edges)
    rows = [("pendant_one_query", 750, sh.cost(4, pendant, sh.optimise(4, pendant, 750))), ("square_all", 4096, sh.cost(4, square, sh.optimise(4, square, 4096))), ("hexagon_all", 500000, sh.cost(6, hexagon, sh.optimise(6, hexagon, 500000)))]
    plans = _over_edges(spark, sf_dir, [(n, k, round(c, 3)) for n, k, c in rows], "workload string, k long, pairs double")
    return plans.select("workload", "k", "pairs", (F.col("pairs") * F.col("m")).alias("shipped"))


register("share_costs", _share_table, f"{_OVER_EDGES} SELECT w AS workload, CAST(k AS BIGINT) AS k, CAST(round(c, 3) AS DOUBLE) AS pairs, CAST(round(c, 3) AS DOUBLE) * m AS shipped FROM z, (VALUES ('pendant_one_query', 750, 65.0), ('square_all', 4096, 4 * sqrt(2 * 4096.0)), ('hexagon_all', 500000, 60000.0)) t(w, k, c)")
register(
    "scheme_formulas",
    lambda spark, sf: _over_edges(spark, sf, [("nodeset", 12, costs.keys("nodeset", 12), float(costs.nodeset_pairs(12))), ("multiway", 6, costs.keys("multiway", 6), float(costs.multiway_pairs(6, True))), ("ordered", 10, costs.keys("ordered", 10), float(costs.ordered_pairs(10)))], "scheme string, b long, k long, pairs double").select("scheme", "b", "k", "pairs", (F.col("pairs") * F.col("m")).alias("shipped")),
    f"{_OVER_EDGES} SELECT scheme, CAST(b AS BIGINT) AS b, CAST(k AS BIGINT) AS k, CAST(pairs AS DOUBLE) AS pairs, CAST(pairs AS DOUBLE) * m AS shipped FROM z, (VALUES ('nodeset', 12, 220, 13.75), ('multiway', 6, 216, 16.0), ('ordered', 10, 220, 10.0)) t(scheme, b, k, pairs)",
)

# counts and roll-ups
_SMALL = ("path3", "star4", "triangle", "diamond", "pendant_triangle", "path4", "square", "k4")
_COUNT = lambda n, graph="copurchase": f"SELECT '{n}' AS pattern, count(*) AS n FROM ({pattern_sql(graph, CATALOGUE[n])})"
_AS_LONG = lambda df, *names: df.withColumns({n: F.col(n).cast("long") for n in names})
register("motif_census", on("copurchase", lambda g: _AS_LONG(census.motif_census(g), "n")), " UNION ALL ".join(_COUNT(n) for n in _SMALL))
_CENSUS_OF = ("copurchase_bulk", "buyer_part")
register(
    "census_by_graph",
    lambda spark, sf: _AS_LONG(census.census_of({n: GRAPHS[n](spark, sf) for n in _CENSUS_OF}), *_SMALL),
    " UNION ALL ".join(f"SELECT '{graph}' AS graph, " + ", ".join(f"(SELECT n FROM ({_COUNT(n, graph)})) AS {n}" for n in _SMALL) for graph in _CENSUS_OF),
)
register(
    "output_bounds",
    on("copurchase", lambda g: measures.bounds(g, census.motif_census(g).where("pattern in ('triangle', 'square', 'k4', 'diamond')"), {"triangle": 3, "square": 4, "k4": 4, "diamond": 4}).select("pattern", F.col("n").cast("long").alias("n"), F.round("of_bound", 9).alias("of_bound"), F.round("of_degree_bound", 9).alias("of_degree_bound"))),
    f"{view('copurchase')}, z AS (SELECT count(*) m, (SELECT max(c) FROM (SELECT count(*) c FROM u GROUP BY src)) d FROM e) SELECT pattern, n, round(CAST(n AS DOUBLE) / power(m, p / 2.0), 9) AS of_bound, round(CAST(n AS DOUBLE) / (m * power(d, p - 2)), 9) AS of_degree_bound FROM z, (" + " UNION ALL ".join(f"SELECT {CATALOGUE[n].p} p, * FROM ({_COUNT(n)})" for n in ("triangle", "square", "k4", "diamond")) + ")",
)


def _census_by_month(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Co-activity within the hour, a graph for each month of events."""
    f = load(spark, sf_dir, "events").where("event_type = 'purchase'").select(F.date_format("ts", "yyyy-MM").alias("month"), F.date_trunc("hour", "ts").alias("g"), F.col("user_id").alias("v"))
    edges = graphs.co_membership_lists(f, "month", "g", "v")
    return census.grouped_census(edges, "month")


register(
    "census_by_month",
    _census_by_month,
    "WITH f AS (SELECT DISTINCT strftime(ts, '%Y-%m') AS month, date_trunc('hour', ts) g, user_id v FROM events WHERE event_type = 'purchase'), e AS MATERIALIZED (SELECT DISTINCT a.month, a.v src, b.v dst FROM f a JOIN f b ON a.month = b.month AND a.g = b.g AND a.v < b.v), d AS (SELECT month, v, count(*) c FROM (SELECT month, src v FROM e UNION ALL SELECT month, dst FROM e) GROUP BY ALL), t AS (SELECT a.month, count(*) n FROM e a JOIN e b ON a.month = b.month AND a.dst = b.src JOIN e c ON c.month = a.month AND c.src = a.src AND c.dst = b.dst GROUP BY 1), p AS (SELECT month, CAST(sum(c * (c - 1)) // 2 AS BIGINT) path3 FROM d GROUP BY 1), m AS (SELECT month, count(*) edges FROM e GROUP BY 1) SELECT month, edges, path3, coalesce(t.n, 0) AS triangles FROM m JOIN p USING (month) LEFT JOIN t USING (month)",
)
_NODE_TRI = f"t AS ({pattern_sql('copurchase', CATALOGUE['triangle'])}), nt AS (SELECT v node, count(*) triangles FROM (SELECT x0 v FROM t UNION ALL SELECT x1 FROM t UNION ALL SELECT x2 FROM t) GROUP BY 1)"
register("topk_nodes_by_triangles", on("copurchase", lambda g: census.node_triangles(g).orderBy(F.desc("triangles"), "node").limit(20)), f"WITH {_NODE_TRI} SELECT * FROM nt ORDER BY triangles DESC, node LIMIT 20")
register(
    "clustering_rank_window",
    on("copurchase", lambda g: census.clustering(g).where("degree > 1").withColumn("rank", F.rank().over(Window.partitionBy("degree").orderBy(F.desc("triangles")))).select("node", "degree", "triangles", F.round("clustering", 9).alias("clustering"), F.col("rank").cast("long").alias("rank"))),
    f"WITH e0 AS ({GRAPH_SQL['copurchase']}), d AS (SELECT v, count(*) c FROM (SELECT src v FROM e0 UNION ALL SELECT dst FROM e0) GROUP BY 1), {_NODE_TRI}, j AS (SELECT v node, c degree, coalesce(triangles, 0) triangles FROM d LEFT JOIN nt ON node = v WHERE c > 1) SELECT node, degree, triangles, round(triangles / (degree * (degree - 1) / 2), 9) AS clustering, rank() OVER (PARTITION BY degree ORDER BY triangles DESC) AS rank FROM j",
)


def _by_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = load(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("node"), "s_nationkey")
    t = census.node_triangles(GRAPHS["cosupply"](spark, sf_dir)).join(s, "node")
    n = load(spark, sf_dir, "nation").select("n_nationkey", "n_name", "n_regionkey")
    return t.join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.sum("triangles").alias("triangles"), F.count("*").alias("suppliers"))


_NODE_TRI_S = f"t AS ({pattern_sql('cosupply', CATALOGUE['triangle'])}), nt AS (SELECT v node, count(*) triangles FROM (SELECT x0 v FROM t UNION ALL SELECT x1 FROM t UNION ALL SELECT x2 FROM t) GROUP BY 1)"
register("motifs_by_nation", _by_nation, f"WITH {_NODE_TRI_S} SELECT n_name, CAST(sum(triangles) AS BIGINT) AS triangles, count(*) AS suppliers FROM nt JOIN supplier ON node = s_suppkey JOIN nation ON n_nationkey = s_nationkey GROUP BY n_name")


def _rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = load(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("node"), "s_nationkey")
    n = load(spark, sf_dir, "nation").join(F.broadcast(load(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    t = census.node_triangles(GRAPHS["cosupply"](spark, sf_dir)).join(s, "node").join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey"))
    return t.rollup("r_name", "n_name").agg(F.sum("triangles").alias("triangles"))


def _cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = load(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("node"), "s_nationkey")
    n = load(spark, sf_dir, "nation").join(F.broadcast(load(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    t = census.node_triangles(GRAPHS["cosupply"](spark, sf_dir)).join(s, "node").join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey"))
    return t.withColumn("even", F.col("node") % 2 == 0).cube("r_name", "even").agg(F.sum("triangles").alias("triangles"), F.percentile("triangles", 0.9).alias("p90"))


register("triangle_cube", _cube, f"WITH {_NODE_TRI_S} SELECT r_name, node % 2 = 0 AS even, CAST(sum(triangles) AS BIGINT) AS triangles, quantile_cont(triangles, 0.9) AS p90 FROM nt JOIN supplier ON node = s_suppkey JOIN nation ON n_nationkey = s_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY CUBE (r_name, even)")
register("triangle_rollup", _rollup, f"WITH {_NODE_TRI_S} SELECT r_name, n_name, CAST(sum(triangles) AS BIGINT) AS triangles FROM nt JOIN supplier ON node = s_suppkey JOIN nation ON n_nationkey = s_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")


def _setops(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = GRAPHS["labelled"](spark, sf_dir).edges
    of = lambda x: e.where(F.col("label") == x).select("src", "dst")
    row = lambda name, df: df.agg(F.count("*").alias("n")).select(F.lit(name).alias("op"), "n")
    return row("union", of("A").union(of("R")).distinct()).unionByName(row("intersect", of("A").intersect(of("R")))).unionByName(row("except", of("A").exceptAll(of("R"))))


_LAB = f"WITH e AS ({GRAPH_SQL['labelled']}), a AS (SELECT src, dst FROM e WHERE label = 'A'), r AS (SELECT src, dst FROM e WHERE label = 'R')"
register("edges_setops", _setops, f"{_LAB} SELECT 'union' AS op, count(*) AS n FROM (SELECT * FROM a UNION SELECT * FROM r) UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM r) UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM r)")


def _streamed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The co-activity graph from the replayed stream; equal to the batch one. A window's members only ever grow, so earlier versions of it add nothing."""
    out, checkpoint = shared_folder(spark, "members"), shared_folder(spark, "checkpoint")
    members = streaming.hourly_members(streaming.event_stream(spark, sf_dir))
    streaming.run_to_folder(members, out, checkpoint)
    return streaming.pairs_of(spark.read.schema(members.schema).parquet(f"{out}/batch=*"))


register("streaming_edges_batch_equiv", _streamed, GRAPH_SQL["coactive"])


def _monthly(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = load(spark, sf_dir, "lineitem").where("l_returnflag = 'R'").select("l_orderkey", "l_partkey")
    months = load(spark, sf_dir, "orders").select("o_orderkey", F.date_format("o_orderdate", "yyyy-MM").alias("month"))
    f = items.join(months, F.col("o_orderkey") == F.col("l_orderkey")).select("month", F.col("l_orderkey").alias("g"), F.col("l_partkey").alias("v")).distinct()
    a, b = f.withColumnRenamed("v", "src"), f.withColumnRenamed("v", "dst")
    per = a.join(b, ["month", "g"]).where("src < dst").select("month", "src", "dst").distinct().groupBy("month").agg(F.count("*").alias("edges"))
    w = Window.orderBy("month").rowsBetween(-2, 0)
    return per.select("month", "edges", F.sum("edges").over(w).alias("moving"))


register("edges_by_month_window", _monthly, "WITH f AS (SELECT DISTINCT strftime(o_orderdate, '%Y-%m') AS month, l_orderkey g, l_partkey v FROM lineitem JOIN orders ON o_orderkey = l_orderkey WHERE l_returnflag = 'R'), p AS (SELECT month, count(*) AS edges FROM (SELECT DISTINCT a.month, a.v, b.v w FROM f a JOIN f b ON a.month = b.month AND a.g = b.g AND a.v < b.v) GROUP BY month) SELECT month, edges, CAST(sum(edges) OVER (ORDER BY month ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS moving FROM p")


# joins in time, windows, numbers, documents
def _asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = load(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    bought, seen = events.where("event_type = 'purchase'").drop("event_type"), events.where("event_type = 'view'")
    return relational.asof_join(bought, seen, ["user_id"], "ts", ["event_id"]).select("event_id", "user_id", "last_event_id")


register("asof_last_view", _asof, "WITH p AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase'), v AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'view') SELECT p.event_id, p.user_id, arg_max(v.event_id, (v.ts, v.event_id)) AS last_event_id FROM p LEFT JOIN v ON v.user_id = p.user_id AND v.ts <= p.ts GROUP BY p.event_id, p.user_id")
register(
    "events_range_window",
    lambda spark, sf: load(spark, sf, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-86_400_000_000, 0)).alias("in_a_day")),
    "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS in_a_day FROM events",
)
register(
    "degree_quartiles",
    on("labelled", lambda g: g.edges.select("label", F.explode(F.array("src", "dst")).alias("node")).groupBy("label", "node").agg(F.count("*").alias("degree")).withColumn("quartile", F.ntile(4).over(Window.partitionBy("label").orderBy("degree", "node")).cast("long"))),
    f"WITH e AS ({GRAPH_SQL['labelled']}), d AS (SELECT label, v AS node, count(*) AS degree FROM (SELECT label, src v FROM e UNION ALL SELECT label, dst FROM e) GROUP BY ALL) SELECT label, node, degree, ntile(4) OVER (PARTITION BY label ORDER BY degree, node) AS quartile FROM d",
)
register(
    "node_numbers",
    on("copurchase", lambda g: relational.numbered(g.degrees().select("degree", "node"), ["degree", "node"])),
    f"{view('copurchase')}, d AS (SELECT src node, count(*) degree FROM u GROUP BY 1) SELECT degree, node, row_number() OVER (ORDER BY degree, node) - 1 AS number FROM d",
)
register(
    "near_docs",
    lambda spark, sf: graphs.near_docs(load(spark, sf, "documents")),
    "WITH l AS (SELECT DISTINCT doc_id v, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) line FROM documents WHERE text IS NOT NULL) WHERE length(line) >= 80), f AS (SELECT line, min(v) u FROM l GROUP BY line) SELECT DISTINCT u AS src, v AS dst FROM l JOIN f USING (line) WHERE u <> v",
)


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
