"""What the driver decides: symmetry, queries, shares, costs, decompositions. Tnn: rows of the survey's list of traps."""

import itertools
import math
import random

import pytest

from motifscan.plans import costs, planner
from motifscan.plans import cqs as Q
from motifscan.plans import shares as S
from motifscan.plans.decompose import decompose, elimination_order, exponents
from motifscan.plans.patterns import CATALOGUE, Pattern, asymmetric_patterns, automorphisms, break_symmetry, cycle

SMALL = [n for n, s in CATALOGUE.items() if 2 < s.p <= 5]
COUNTS = {"triangle": (1, 6, 1), "square": (3, 14, 3), "pendant_triangle": (12, 12, 6), "diamond": (6, 18, 6), "k4": (1, 24, 1), "path3": (3, 4, 3), "path4": (12, 8, 4), "star4": (4, 8, 4), "star5": (5, 16, 5), "pentagon": (12, 30, 3), "house": (60, 42, 21), "bowtie": (15, 36, 6), "k5": (1, 120, 1)}


@pytest.mark.parametrize("name", SMALL)
def test_every_instance_once(name):
    s = CATALOGUE[name]
    for queries in (Q.cqs_by_orders(s), Q.merge_by_orientation(s), Q.cqs_by_orientation(s), Q.cqs_by_orientation(s, "bidirectional")):
        assert all(Q.found_once(s, queries, r) == 1 for r in itertools.permutations(range(s.p)))


@pytest.mark.parametrize("name", COUNTS)
def test_numbers_of_queries(name):
    s = CATALOGUE[name]
    assert (len(Q.order_classes(s)), len(Q.acyclic_orientations(s)), len(Q.cqs_by_orientation(s))) == COUNTS[name]


def test_disconnected_patterns():
    for s in (Pattern(4, ((0, 1),)), Pattern(4, ((0, 1), (2, 3)))):
        assert all(Q.found_once(s, Q.cqs_by_orientation(s), r) == 1 for r in itertools.permutations(range(4)))


def test_user_inequalities():
    assert len(Q.cqs_by_orders(CATALOGUE["pendant_triangle"], ((2, 3),))) == 12
    with pytest.raises(ValueError):
        Q.cqs_by_orders(CATALOGUE["square"], ((0, 1),))


def test_adjacent_swap_merges_to_difference():
    merged = Q.merge_by_orientation(CATALOGUE["pendant_triangle"])
    assert len(merged) == 6 and not any(q.orders for q in merged) and any(q.differ for q in merged)


@pytest.mark.parametrize("p", range(3, 9))
def test_cycle_queries(p):
    """T11-T15: 8 for the hexagon, 9 for the heptagon, exactly once."""
    queries = Q.cycle_cqs(p)
    assert len(queries) == Q.cycle_cq_count(p) == {3: 1, 4: 3, 5: 3, 6: 8, 7: 9, 8: 21}[p]
    rng = random.Random(p)
    ranks = list(itertools.permutations(range(p))) if p < 6 else [rng.sample(range(p), p) for _ in range(120)]
    assert all(Q.found_once(cycle(p), queries, r) == 1 for r in ranks)


def test_cycle_counts_and_bound():
    assert [Q.cycle_cq_count(p) for p in range(3, 13)] == [1, 3, 3, 8, 9, 21, 29, 61, 93, 191]
    assert all(Q.cycle_cq_bound(p) <= Q.cycle_cq_count(p) for p in range(3, 13))
    assert Q.cycle_cq_bound(7) == 9


def test_literal_remedies_fail_on_hexagons():
    rng = random.Random(1)
    found = [Q.found_once(cycle(6), Q.cycle_cqs(6, strict_text=True), rng.sample(range(6), 6)) for _ in range(400)]
    assert set(found) != {1}


def test_run_sequences():
    assert Q.updown((4, 1)) == "uuuud" and Q.flip("uuuud") == "udddd" and Q.flip(Q.flip("uuudd")) == "uuudd"
    assert set(Q.even_bags(5)) == {(1, 4), (2, 3), (1, 1, 1, 2)}
    assert {tuple(sorted(r)) for r in Q.run_classes(5)} == set(Q.even_bags(5))
    assert Q.characteristic_sequence([3, 1, 2, 5, 4]) == (2, 3) and Q.characteristic_sequence([1, 4, 2, 5, 3]) == (1, 1, 1, 2)


def test_symmetry_is_broken_to_the_least_image():
    for s in CATALOGUE.values():
        if s.p <= 5:
            group = automorphisms(s)
            for r in itertools.islice(itertools.permutations(range(s.p)), 40):
                images = [tuple(r[g[v]] for v in range(s.p)) for g in group]
                fit = [i for i in images if all(i[a] < i[b] for a, b in break_symmetry(group))]
                assert fit == [min(images)] * len(fit) and len(set(fit)) == 1


def test_asymmetric_patterns():
    """T22"""
    assert len(asymmetric_patterns(6)) == 8 and not asymmetric_patterns(5)


def test_shares_of_one_query():
    ts = tuple(S.Term(a, b) for a, b in CATALOGUE["pendant_triangle"].edges)
    best = S.optimise(4, ts, 750)
    assert best == pytest.approx([1, 30, 5, 5]) and S.cost(4, ts, best) == pytest.approx(65)
    assert S.dominated(4, ts) == {0}
    assert S.round_shares(4, ts, best, 750) == [1, 30, 5, 5]


def test_shares_of_all_square_queries():
    """T9: 4 sqrt(2k)."""
    s = CATALOGUE["square"]
    ts = S.terms(s, Q.cqs_by_orientation(s))
    best = S.optimise(4, ts, 4096)
    assert S.cost(4, ts, best) == pytest.approx(4 * math.sqrt(2 * 4096))
    assert S.sums(4, ts, best) == pytest.approx([S.sums(4, ts, best)[0]] * 4)
    rng = random.Random(2)
    for _ in range(200):
        other = [x * math.exp(rng.uniform(-0.5, 0.5)) for x in best]
        f = (4096 / math.prod(other)) ** 0.25
        assert S.cost(4, ts, [x * f for x in other]) >= S.cost(4, ts, best) - 1e-6


def test_hexagon_shares():
    """T6: shares 5 and 10; 60,000 pairs an edge."""
    assert S.cycle_shares(6, 500_000) == pytest.approx([5, 10, 10, 10, 10, 10])
    ts = tuple(S.Term(a, b, 1.0 if 0 in (a, b) else 2.0) for a, b in cycle(6).edges)
    assert S.cost(6, ts, S.cycle_shares(6, 500_000)) == pytest.approx(60_000)
    assert S.cost(6, ts, S.optimise(6, ts, 500_000)) == pytest.approx(60_000)
    assert S.two_class_shares(cycle(6), {e for e in cycle(6).edges if 0 not in e}, 500_000) == pytest.approx([5, 10, 10, 10, 10, 10])


@pytest.mark.parametrize("name", ["triangle", "square", "pentagon", "k4", "k5", "cube"])
def test_regular_patterns_have_equal_shares(name):
    s = CATALOGUE[name]
    ts = tuple(S.Term(a, b) for a, b in s.edges)
    assert S.cost(s.p, ts, S.optimise(s.p, ts, 1000)) == pytest.approx(S.cost(s.p, ts, S.regular_shares(s, 1000)))


def test_three_classes():
    """T7, T8: a/b = 2^(2/3), z/b = 2^(1/3) where each class has half of each kind of neighbours, and the closed form's cost; against the solver."""
    ring = lambda at: [(at, at + 1), (at + 1, at + 2), (at + 2, at + 3), (at, at + 3)]
    across = lambda at: [(at + i, 8 + (i + j) % 4) for i in range(4) for j in (0, 1)]
    s = Pattern(12, tuple(sorted([*ring(0), *ring(4), *across(0), *across(4)])))
    both = {e for e in s.edges if e[0] < 4}
    assert S.three_classes(s, both) == S.ThreeClasses(frozenset(range(4)), frozenset(range(8, 12)), frozenset(range(4, 8)))
    found, k = S.three_class_shares(s, both, 4096.0), 4096.0
    a, z, b = found[0], found[8], found[4]
    assert (a / b, z / b, z) == pytest.approx((2 ** (2 / 3), 2 ** (1 / 3), k ** (1 / 12)))
    ts = tuple(S.Term(u, v, 2.0 if (u, v) in both else 1.0) for u, v in s.edges)
    assert S.cost(12, ts, found) == pytest.approx(S.replication_equal_thirds(12, 4, k)) == pytest.approx(S.cost(12, ts, S.optimise(12, ts, k)), rel=1e-4)


def test_three_classes_that_cover():
    """T9, T23: mixed nodes that are independent and cover all edges; only the product of the outer shares counts then."""
    s, both = CATALOGUE["square"], {(1, 2), (2, 3)}
    assert S.three_classes(s, both) == S.ThreeClasses(frozenset({2}), frozenset({1, 3}), frozenset({0}))
    found = S.three_class_shares(s, both, 4096.0)
    ts = tuple(S.Term(u, v, 2.0 if (u, v) in both else 1.0) for u, v in s.edges)
    assert S.cost(4, ts, found) == pytest.approx(S.replication_covering(4, 2, 4096, 1)) == pytest.approx(4 * math.sqrt(2 * 4096))
    assert found[2] == pytest.approx(2 * found[0])
    cover = CATALOGUE["k33"]
    both = {(0, 3), (0, 4), (0, 5)}
    ts = tuple(S.Term(u, v, 2.0 if (u, v) in both else 1.0) for u, v in cover.edges)
    assert S.cost(6, ts, S.optimise(6, ts, 1e4)) == pytest.approx(S.replication_covering(6, 3, 1e4, 2), rel=1e-4)


@pytest.mark.parametrize(("option", "name", "both"), [("a=z", "pentagon", {(0, 1), (1, 2), (2, 3)}), ("b=z", "pentagon", {(0, 1), (1, 2)}), ("a=z", "prism", {(0, 1), (0, 2), (0, 3), (1, 2), (1, 4), (3, 4)}), ("b=z", "cube", {(1, 3), (2, 3), (3, 7)})])
def test_classes_of_equal_shares(option, name, both):
    """Two of the three values may be equal, where all sums come out equal; all three never."""
    s = CATALOGUE[name]
    found, c = S.three_class_shares(s, both, 500.0, option), S.three_classes(s, both)
    ts = tuple(S.Term(u, v, 2.0 if (u, v) in both else 1.0) for u, v in s.edges)
    assert math.prod(found) == pytest.approx(500) and S.cost(s.p, ts, found) == pytest.approx(S.cost(s.p, ts, S.optimise(s.p, ts, 500.0)), rel=1e-4)
    alike = c.s2 | (c.s1 if option == "a=z" else c.s3)
    assert len({round(found[v], 9) for v in alike}) == 1 and S.class_consistency(s, both)
    assert S.three_class_shares(s, both, 500.0, "a=b=z") is None
    assert not S.class_consistency(CATALOGUE["hexagon"], {(0, 1), (1, 2), (3, 4)}) and not S.class_consistency(CATALOGUE["cube"], {(0, 1), (0, 2)})


@pytest.mark.parametrize("name", ["square", "pendant_triangle", "pentagon"])
def test_together_is_never_worse(name):
    for k in (64, 4096):
        c = planner.compare_grouping(CATALOGUE[name], k)
        assert c["joint"] <= 2 * c["best_single"] + 1e-6 and c["joint"] <= c["separate"] + 1e-6


def test_cost_formulas():
    """T1"""
    assert (costs.nodeset_pairs(12), costs.multiway_pairs(6, True), costs.multiway_pairs(6), costs.ordered_pairs(10)) == (13.75, 16, 18, 10)
    assert [costs.keys(*a) for a in (("nodeset", 12), ("multiway", 6), ("ordered", 10))] == [220, 216, 220]
    assert costs.asymptotic("nodeset", 1e6) / costs.asymptotic("ordered", 1e6) == pytest.approx(1.5)
    assert costs.asymptotic("multiway", 1e6) / costs.asymptotic("ordered", 1e6) == pytest.approx(3 / 6 ** (1 / 3))
    for p in (3, 4, 5):
        assert costs.nodeset_pairs(4000, p) / costs.bucket_pairs(4000, p) == pytest.approx(costs.nodeset_over_bucket(p), rel=1e-2)


def test_decompositions():
    assert {n: exponents(CATALOGUE[n]) for n in ("square", "house", "bowtie", "prism", "k5", "star4", "path3")} == {"square": (0, 2), "house": (0, 2.5), "bowtie": (0, 2.5), "prism": (0, 3), "k5": (0, 2.5), "star4": (2, 1), "path3": (1, 1)}
    for s in CATALOGUE.values():
        assert costs.is_convertible(*exponents(s), s.p)
        assert sorted(v for part in decompose(s).all() for v in part) == list(range(s.p))
        order = elimination_order(s)
        assert all(s.neighbours(v) & set(order[:i]) for i, v in enumerate(order) if i)


def test_planner_prefers_degree_order_on_sparse_graphs():
    assert planner.plan(CATALOGUE["triangle"], 10_000, m=132_580, two_paths=436_712).name == "degree"
    assert planner.plan(CATALOGUE["square"], 32).name in ("bucket", "variable")
    assert planner.plan(CATALOGUE["square"], 10**9, max_degree=3).name == "bounded"
    assert planner.plan(CATALOGUE["triangle"], m=10**6, edges_per_key=10**3).b >= planner.plan(CATALOGUE["triangle"], m=10**6, edges_per_key=10**4).b > 1
    with pytest.raises(ValueError):
        planner.plan(CATALOGUE["square"])


@pytest.mark.parametrize("name", ["square", "pendant_triangle", "pentagon", "diamond", "path4"])
def test_cheapest_images(name):
    """Still one query for each class, which find all; no choice of images ships less."""
    s = CATALOGUE[name]
    picked, plain = planner.cheapest_queries(s, 64), Q.cqs_by_orientation(s, "bidirectional")
    assert len(picked) == len(plain)
    for rank in itertools.islice(itertools.permutations(range(s.p)), 60):
        assert Q.found_once(s, picked, rank) == 1
    assert Q.bidirectional(picked) <= Q.bidirectional(plain)
    price = lambda qs: S.cost(s.p, S.terms(s, qs), S.optimise(s.p, S.terms(s, qs), 64))
    assert price(picked) <= price(plain) + 1e-6 or Q.bidirectional(picked) < Q.bidirectional(plain)


def test_planner_says_when_degrees_are_too_low():
    assert planner.plan(CATALOGUE["square"], 10**4, max_degree=4, n=10**6).note or planner.plan(CATALOGUE["square"], 10**4, max_degree=4, n=10**6).name != "bucket"
    assert not planner.plan(CATALOGUE["square"], 8, max_degree=10**4, n=10**6).note
    assert not costs.degree_ok(4, 10, 10**6) and costs.degree_ok(10**4, 10, 10**6)


def test_useful_keys():
    """Only lists that never fall own an instance: of the complete graph on 4 nodes a bucket, ordered by bucket, every such list has some."""
    for b, p in ((3, 3), (2, 4), (4, 2)):
        nodes = sorted((v % b, v) for v in range(4 * b))
        owned = {tuple(n[0] for n in c) for c in itertools.combinations(nodes, p)}
        assert owned == set(costs.useful_keys(b, p)) and len(owned) == math.comb(b + p - 1, p)
