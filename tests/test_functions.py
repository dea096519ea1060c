"""Symmetry, orders and cost: values, theorems and properties."""

import random
from itertools import permutations

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from knotwork import oracle
from knotwork.functions import cost, orders, symmetry
from knotwork.functions.pattern import CATALOG, Pattern, canonical, clique, connected_patterns, cycle, known_name, near_clique, parse, path
from knotwork.operators.baselines import topological_program
from knotwork.plans.program import compile_cached, compile_program, merge, near_best

NAMES = [n for n, p in CATALOG.items() if p.k <= 6]


def brute(p):
    return {g for g in permutations(range(p.k)) if all(p.has(g[i], g[j]) for i, j in p.edges)}


@pytest.mark.parametrize("name", NAMES)
def test_automorphisms_equal_brute_force(name):
    assert set(symmetry.automorphisms(CATALOG[name])) == brute(CATALOG[name])


@pytest.mark.parametrize("row", oracle.CENSUS, ids=lambda r: r[0])
def test_census(row):
    name, k, autos, valid, kinds, best, worst = row
    c, r = orders.census(CATALOG[name]), cost.ranked(CATALOG[name])
    assert (c["k"], c["autos"], c["valid"], c["distinct"]) == (k, autos, valid, kinds)
    assert (round(r[0][0], 2), round(r[-1][0], 2)) == (best, worst)


def test_pattern_totals():
    assert [len(connected_patterns(k)) for k in range(3, 8)] == [2, 6, 21, 112, 853]
    for k, valid, kinds in oracle.ORDER_TOTALS:
        cs = [orders.census(p) for p in connected_patterns(k)]
        assert (sum(c["valid"] for c in cs), sum(c["distinct"] for c in cs)) == (valid, kinds)


def test_rectangle_example():
    p = CATALOG["rectangle"]
    assert set(symmetry.bounds_full(p, (0, 1, 2, 3))) == {(0, 1), (0, 2), (0, 3), (1, 2)}
    assert symmetry.bounds_min(p, (0, 1, 2, 3)) == {1: 0, 2: 1, 3: 0}
    assert symmetry.is_valid_mapping(p, (0, 2, 1, 3)) and not symmetry.is_valid_mapping(p, (0, 2, 3, 1))


def test_multiplicities_of_the_baseline():
    assert symmetry.multiplicity(CATALOG["near_clique_7"]) == 240
    assert topological_program("near_clique_7").multiplicity == 120
    assert symmetry.multiplicity(CATALOG["pentagon"]) == 10 and topological_program("pentagon").multiplicity == 5
    assert symmetry.multiplicity(cycle(7)) == 14 and symmetry.multiplicity(clique(7)) == 5040 and symmetry.multiplicity(near_clique(7)) == 240


@pytest.mark.parametrize("name", NAMES)
def test_one_bound_implies_all_and_its_trees_multiply_to_the_group(name):
    p = CATALOG[name]
    for o in orders.distinct(p):
        least = [(u, w) for w, u in symmetry.bounds_min(p, o).items()]
        assert symmetry.closure(least) == symmetry.closure(symmetry.bounds_full(p, o))
        assert cost.prefix_probability(o, symmetry.bounds_min(p, o), p.k) == pytest.approx(1 / symmetry.multiplicity(p))


@settings(max_examples=60, deadline=None)
@given(st.sampled_from(NAMES), st.randoms(use_true_random=False))
def test_exactly_one_relabelling_obeys_the_bounds(name, rnd):
    p = CATALOG[name]
    o = rnd.choice(orders.distinct(p))
    ids = rnd.sample(range(1000), p.k)
    for form in ("full", "min"):
        ok = [g for g in symmetry.automorphisms(p) if all(ids[g[u]] > ids[g[w]] for u, w in symmetry.bounds(p, o, form))]
        assert len(ok) == 1


@pytest.mark.parametrize("name", [n for n in NAMES if CATALOG[n].k <= 5])
def test_searches_agree(name):
    p = CATALOG[name]
    every = set(orders.by_permutation(p))
    assert every == set(orders.by_prefix(p)) and all(orders.is_valid(p, o) for o in every)
    kinds = orders.distinct(p)
    assert len(kinds) * symmetry.multiplicity(p) == len(every)
    assert all(not orders.equivalent(p, a, b) for i, a in enumerate(kinds) for b in kinds[:i])
    assert all(any(orders.equivalent(p, o, k) for k in kinds) for o in every)


@pytest.mark.parametrize("name", [n for n in NAMES if CATALOG[n].k <= 5])
def test_prefix_probability_equals_counting(name):
    p = CATALOG[name]
    for o in orders.distinct(p)[:4]:
        b = symmetry.bounds_min(p, o)
        for i in range(1, p.k + 1):
            perms = list(permutations(range(i)))
            good = sum(all(ids[o.index(u)] > ids[o.index(w)] for w, u in b.items() if u in o[:i] and w in o[:i]) for ids in perms)
            assert cost.prefix_probability(o, b, i) == pytest.approx(good / len(perms))


def test_paths_have_powers_of_two():
    for n in range(3, 7):
        c = orders.census(path(n))
        assert (c["valid"], c["distinct"]) == (2 ** (n - 1), 2 ** (n - 2))


def test_tailed_triangle_orders():
    p = CATALOG["tailed_triangle"]
    q = p.relabel((0, 1, 2, 3))
    assert orders.equivalent(q, (0, 1, 2, 3), (1, 0, 2, 3))
    assert cost.choose(p)[:3] in [tuple(x) for x in permutations((0, 1, 2))]  # triangle first


def test_parse_and_canonical():
    assert canonical(parse("x-y,y-z,z-w,w-x")) == canonical(CATALOG["rectangle"])
    assert known_name(parse("a-b, b-c, c-a")) == "triangle"
    for bad in ("", "a-b,c-d", "a-a", "a-b,,*"):
        with pytest.raises(ValueError):
            parse(bad)
    rnd = random.Random(1)
    for p in connected_patterns(5):
        g = rnd.sample(range(5), 5)
        assert canonical(p.relabel(g)).edge_mask == p.edge_mask


def test_guards_and_programs():
    p = compile_program(CATALOG["rectangle"], (0, 1, 2, 3))
    assert p.explain().split("\n")[1:] == ["B in N(A), B < A", "C in N(A) - N(B), C < B (no edge)", "D in N(B) & N(C) - N(A), D < A (no edge)"]
    assert p.levels[2].oriented == (0,)  # A lies above C only through B
    free = compile_program(CATALOG["rectangle"], (0, 1, 2, 3), form="none")
    assert free.levels[2].distinct == (1,) and free.levels[3].distinct == (0,)
    assert all(len(x.below) <= 1 for n in NAMES for x in compile_program(CATALOG[n]).levels)
    with pytest.raises(ValueError):
        compile_program(path(3), (0, 2, 1))


def test_trie_shares_levels_and_cache_knows_isomorphs():
    root, picked = merge([near_best(p) for p in connected_patterns(4)])
    assert len(picked) == 6 and root.size() - 1 < sum(p.k for p in picked)
    compile_cached(CATALOG["house"])
    assert compile_cached(CATALOG["house"].relabel((4, 3, 2, 1, 0)))[1] == 0.0


@pytest.mark.parametrize("k", [3, 4, 5])
def test_pruned_choice_is_the_cheapest_distinct_order(k):
    models = (cost.ModelGraph(), cost.ModelGraph(500, 0.2), cost.ModelGraph(1000, 0.005, closing=0.4))
    for p in [*connected_patterns(k), *(CATALOG.values() if k == 5 else ())]:
        for g in models if p.k <= 6 else models[:1]:
            for early in (False, True):
                assert cost.choose(p, g, early) == cost.ranked(p, g, early_exit=early)[0][1]


def test_fitted_model_and_early_exit():
    g = cost.ModelGraph.from_stats(100, 300, triangles=20, wedges=600)
    assert g.p == pytest.approx(600 / 9900) and g.closing == pytest.approx(0.1)
    for n in ("rectangle", "house"):
        o = cost.choose(CATALOG[n])
        assert cost.order_cost(CATALOG[n], o, early_exit=True) <= cost.order_cost(CATALOG[n], o)
    assert Pattern.of(2, [(0, 1)]).connected
