"""Costs, trees, graphs: worked examples and identities; no Spark."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from codetrees.functions import codelen
from codetrees.plans.model import LEAF, Closure, Model, count_between, itemsets_of_leaf, itemsets_of_tree, join_trees, leaves, mask_of, split_leaf, sources_of, topological_order


def by_definition(m):
    return math.log2(sum(math.comb(m, k) * (k / m) ** k * ((m - k) / m) ** (m - k) for k in range(m + 1))) if m else 0.0


def test_leaf_complexity_values():
    want = {0: 0, 1: 1, 2: 1.321928, 3: 1.530515, 10: 2.220397, 50: 3.254462, 100: 3.723554, 1000: 5.332823, 2000: 5.825758, 60000: 8.265217}
    for m, bits in want.items():
        assert float(codelen.nml_bits(m)) == pytest.approx(bits, abs=1e-6)
        assert codelen.nml_exact(m) == pytest.approx(bits, abs=1e-6)


@given(st.integers(0, 300))
@settings(max_examples=60, deadline=None)
def test_leaf_complexity_is_the_definition(m):
    assert codelen.nml_exact(m) == pytest.approx(by_definition(m), abs=1e-9)


def test_series_meets_exact_values():
    assert float(codelen.nml_asymptotic(50)) == pytest.approx(codelen.nml_exact(50), abs=2e-6)
    assert float(codelen.nml_asymptotic(10_000)) == pytest.approx(codelen.nml_exact(10_000), abs=1e-9)


def test_refined_tends_to_bic():
    assert codelen.nml_exact(10**6) - 0.5 * math.log2(10**6) == pytest.approx(0.5 * math.log2(math.pi / 2), abs=2e-3)


def test_worked_bits():
    assert float(codelen.data_bits(2, 1)) / 2 == 1
    assert float(codelen.data_bits([50, 50], [15, 5]).sum()) / 100 == pytest.approx(0.675143, abs=1e-6)
    cost = float(codelen.leaf_cost([50, 50], [15, 5]).sum()) + codelen.split_cost(3)
    assert cost == pytest.approx(78.608211, abs=1e-6)


def test_empty_and_pure_leaves_cost_no_data():
    assert float(codelen.data_bits(0, 0)) == 0 and float(codelen.data_bits(7, 7)) == 0 and float(codelen.data_bits(7, 0)) == 0


@given(st.integers(1, 200), st.integers(1, 200))
@settings(max_examples=60, deadline=None)
def test_pure_leaves_never_gain(a, b):
    assert codelen.nml_exact(a + b) <= codelen.nml_exact(a) + codelen.nml_exact(b) + 1e-12


def test_split_costs_grow_with_items():
    assert codelen.split_cost(4) == 3 and codelen.split_cost(1024) == 11


A, B, C = 0, 1, 2
ON_A_THEN_B = ("test", A, LEAF, ("test", B, LEAF, LEAF))


def test_sources_and_itemsets_of_a_tree():
    assert sources_of(ON_A_THEN_B) == {A, B}
    got = [itemsets_of_leaf(C, mask_of(p), mask_of(n)) for p, n in leaves(ON_A_THEN_B)]
    assert got[0] == {0b001, 0b101}
    assert got[1] == {0b010, 0b011, 0b110, 0b111}
    assert got[2] == set(range(8))
    assert itemsets_of_tree(C, ON_A_THEN_B) == set(range(8))


def test_cyclic_trees_are_rejected():
    names = ["a", "b", "c"]
    on = lambda i: ("test", i, LEAF, LEAF)
    with pytest.raises(ValueError):
        Model(names, 1, [on(C), on(A), ON_A_THEN_B]).validate()
    m = Model(names, 1, [LEAF, on(A), ON_A_THEN_B]).validate()
    assert m.order() == [A, B, C]
    with pytest.raises(ValueError):
        Model(names, 1, [on(A), LEAF, LEAF]).validate()


def test_split_and_join():
    t = split_leaf(LEAF, frozenset(), frozenset(), A)
    t = split_leaf(t, frozenset(), frozenset({A}), B)
    assert t == ON_A_THEN_B == join_trees(A, LEAF, ("test", B, LEAF, LEAF))
    with pytest.raises(ValueError):
        split_leaf(t, frozenset({A}), frozenset(), A)
    with pytest.raises(ValueError):
        join_trees(B, LEAF, ("test", B, LEAF, LEAF))


def test_long_negative_paths_raise():
    with pytest.raises(ValueError):
        itemsets_of_leaf(40, 0, (1 << 30) - 1)


@given(st.lists(st.tuples(st.integers(0, 5), st.integers(0, 5)), max_size=14))
@settings(max_examples=80, deadline=None)
def test_closure_agrees_with_sorting(edges):
    c, kept = Closure(6), []
    for s, d in edges:
        cyclic = topological_order(6, [*kept, (s, d)]) is None
        assert c.would_cycle(s, d) == cyclic
        if not cyclic:
            c.add(s, d)
            kept.append((s, d))


def test_json_round_trip():
    m = Model(["a", "b", "c"], 10, [LEAF, LEAF, ON_A_THEN_B], {(0, 0, 0): (10, 4), (1, 0, 0): (10, 5), (2, 1, 0): (4, 1), (2, 2, 1): (3, 3), (2, 0, 3): (3, 0)})
    back = Model.from_json(m.to_json())
    assert back.trees == m.trees and back.counts == m.counts and back.cost() == m.cost()
    assert np.isfinite(m.cost()) and m.signatures() == [["c", "a", "b"]] and m.packed_by("a") == ["c"] and "a?" in m.explain(2)


@pytest.mark.parametrize("seed", range(30))
def test_itemsets_are_counted_without_listing(seed):
    r = np.random.default_rng(seed)
    k = int(r.integers(1, 9))
    spans = set()
    for _ in range(int(r.integers(0, 12))):
        a, b = (int(x) for x in r.integers(0, 1 << k, 2))
        spans.add((a & b, a | b))
    assert count_between(spans) == sum(any(low & ~m == 0 and m & ~high == 0 for low, high in spans) for m in range(1 << k))


def test_leaves_of_many_negative_tests_are_counted():
    tree = LEAF
    for i in range(1, 60):
        tree = ("test", i, LEAF, tree)
    m = Model([f"i{i}" for i in range(60)], 10, [tree] + [LEAF] * 59, {})
    assert m.count_itemsets(True) == 1 << 60 and m.count_itemsets() == (1 << 60) - 1
    small = Model([f"i{i}" for i in range(12)], 10, [ON_A_THEN_B] + [LEAF] * 11, {})
    assert small.count_itemsets() == len(small.itemsets()) and small.count_itemsets(True) == len(small.itemsets(True))
