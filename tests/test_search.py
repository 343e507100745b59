"""Growth, constrained trees, spanning trees, selection: against brute force on small data; no Spark."""

from itertools import product

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from codetrees.functions import codelen
from codetrees.operators.itemsets import all_itemsets, mine_frequent, mine_low_entropy, with_supports
from codetrees.plans import select as sel
from codetrees.plans.counts import LocalCounts
from codetrees.plans.cover import cover_baseline
from codetrees.plans.greedy import fixed_trees_model, grow_model, grow_naively, leaf_gains
from codetrees.plans.model import LEAF, Closure, independent_cost, itemsets_of_tree, leaves, mask_of, sources_of


def counts_from(rows: np.ndarray) -> LocalCounts:
    k = rows.shape[1]
    m = (rows.astype(np.int64) << np.arange(k)).sum(1)
    u, n = np.unique(m, return_counts=True)
    return LocalCounts(u.view(np.uint64).reshape(-1, 1), n, k)


def chain(n=2000, k=6, flip=0.1, seed=1) -> np.ndarray:
    rng = np.random.default_rng(seed)
    x = np.zeros((n, k), bool)
    x[:, 0] = rng.random(n) < 0.5
    for i in range(1, k):
        x[:, i] = x[:, i - 1] ^ (rng.random(n) < flip)
    return x


def noise(n=400, k=5, seed=2) -> np.ndarray:
    rng = np.random.default_rng(seed)
    x = rng.random((n, k)) < 0.4
    x[:, 2] |= x[:, 0] & x[:, 1]
    x[:, 3] = x[:, 2] ^ (rng.random(n) < 0.15)
    return x


def names(k):
    return [f"a{i}" for i in range(k)]


def test_chain_gives_singles_and_neighbour_pairs():
    c = counts_from(chain())
    m = grow_model(c, names(6))
    assert m.itemsets() >= {1 << i for i in range(6)} | {3 << i for i in range(5)}
    assert 45 < 100 * m.cost() / independent_cost([c.path(0, 0, i)[1] for i in range(6)], c.total) < 65


def test_independent_items_are_left_alone():
    x = np.random.default_rng(5).random((2000, 8)) < 0.5
    assert grow_model(counts_from(x), names(8)).trace == []


@pytest.mark.parametrize("criterion", codelen.CRITERIA)
def test_growth_is_the_definition(criterion):
    for seed in range(4):
        c = counts_from(noise(seed=seed))
        a, b = grow_model(c, names(5), criterion), grow_naively(c, names(5), criterion)
        assert [t[:4] for t in a.trace] == [t[:4] for t in b.trace]


def test_growth_certificates():
    c = counts_from(noise(n=1500))
    m = grow_model(c, names(5))
    assert m.validate().cost() == pytest.approx(m.trace[-1][5])
    totals = [t[5] for t in m.trace]
    assert totals == sorted(totals, reverse=True)
    again = fixed_trees_model(c, names(5), m.trees)
    assert again.counts == m.counts
    g = Closure(5)
    for s, d in m.edges():
        g.add(s, d)
    for t, pos, neg in m.counts:  # no legal split is left that saves
        gain = leaf_gains(c, 5, t, pos, neg)[2]
        assert all(gain[j] <= 1e-9 or g.would_cycle(t, j) for j in range(5))


def test_fixed_order_and_limits():
    c = counts_from(chain())
    m = grow_model(c, names(6), order=[5, 4, 3, 2, 1, 0])
    assert all(s > t for t, s in m.edges())
    assert len(grow_model(c, names(6), max_splits=2).trace) == 2
    assert max(len(p) + len(n) for tree in grow_model(c, names(6), max_depth=1).trees for p, n in leaves(tree)) <= 1


def test_metamorphic():
    x = noise(n=600)
    c = counts_from(x)
    m = grow_model(c, names(5))
    shuffled = counts_from(np.random.default_rng(0).permutation(x))
    assert grow_model(shuffled, names(5)).cost() == m.cost()
    y = x.copy()
    y[:, 1] ^= True  # zeros and ones are alike
    assert grow_model(counts_from(y), names(5)).cost() == pytest.approx(m.cost())
    twice = fixed_trees_model(counts_from(np.concatenate([x, x])), names(5), m.trees)
    assert twice.data_bits() == pytest.approx(2 * m.data_bits())
    constant = np.column_stack([x, np.ones(len(x), bool)])
    assert all(5 not in sources_of(t) for t in grow_model(counts_from(constant), names(6)).trees)


@pytest.mark.parametrize("rows", [np.zeros((0, 3), bool), np.ones((1, 3), bool), np.ones((50, 1), bool), np.zeros((20, 3), bool)])
def test_edge_data(rows):
    m = grow_model(counts_from(rows), names(rows.shape[1]))
    assert m.trace == [] and np.isfinite(m.cost())


def brute_best(family, k, t, sources, pos=0, neg=0):
    f = sel.TreeSearch(family, k)
    best = f.leaf(t, pos, neg)[0]
    for b in range(k):
        path = pos | neg | 1 << t
        if sources >> b & 1 and not path >> b & 1 and path | 1 << b in family:
            best = min(best, codelen.split_cost(k) + brute_best(family, k, t, sources, pos | 1 << b, neg) + brute_best(family, k, t, sources, pos, neg | 1 << b))
    return best


def test_best_tree_against_brute_force():
    c = counts_from(noise())
    for minsup in (1, 40, 120):
        family = mine_frequent(c, 5, minsup, 4)
        f, plain = sel.TreeSearch(family, 5), sel.TreeSearch(family, 5, memo=False)
        for t in range(5):
            if 1 << t in family:
                cost, tree = f.best_tree(t, 0b11111 & ~(1 << t))
                assert cost == pytest.approx(brute_best(family, 5, t, 0b11111 & ~(1 << t)))
                assert plain.best_tree(t, 0b11111)[0] == pytest.approx(cost)
                assert sel.TreeSearch(family, 5, data=c).best_tree(t, 0b11111)[0] == pytest.approx(cost)
                assert all(s in family for s in itemsets_of_tree(t, tree))
                assert sel.TreeSearch(family, 5, "greedy").best_tree(t, 0b11111)[0] >= cost - 1e-9


def test_leaf_counts_by_inclusion_and_exclusion():
    c = counts_from(noise())
    s = sel.Supports(all_itemsets(c, 5, 5))
    for pos, neg in product(range(32), repeat=2):
        if not pos & neg:
            assert s.count(pos, neg) == c.path(pos, neg, 0)[0]


def brute_tree(k, w):
    best = None
    for up in product(range(-1, k), repeat=k):
        if any((i, up[i]) not in w for i in range(k)):
            continue
        ok = True
        for i in range(k):
            v, seen = i, set()
            while v != -1 and v not in seen:
                seen.add(v)
                v = up[v]
            ok &= v == -1
        if ok:
            total = sum(w[i, up[i]] for i in range(k))
            best = total if best is None else min(best, total)
    return best


@given(st.integers(2, 5), st.randoms(use_true_random=False))
@settings(max_examples=60, deadline=None)
def test_spanning_tree_against_brute_force(k, rng):
    w = {(i, j): rng.randint(0, 9) for i in range(k) for j in range(-1, k) if i != j and (j == -1 or rng.random() < 0.8)}
    up = sel.min_arborescence([*range(k), -1], -1, [(i, j, x) for (i, j), x in w.items()])
    assert sum(w[i, up[i]] for i in range(k)) == brute_tree(k, w)


def test_spanning_tree_cases():
    nested = [(0, 1, 1), (1, 0, 1), (1, 2, 2), (2, 0, 1), (0, -1, 10), (1, -1, 9), (2, -1, 9)]
    assert sum(dict(((a, b), c) for a, b, c in nested)[i, sel.min_arborescence([0, 1, 2, -1], -1, nested)[i]] for i in range(3)) == 11
    tie = [(0, -1, sel._weight(5.0, False, 0, -1, 2)), (0, 1, sel._weight(5.0, True, 0, 1, 2)), (1, -1, sel._weight(1.0, False, 1, -1, 2))]
    assert sel.min_arborescence([0, 1, -1], -1, tie)[0] == -1  # equal weight: the sink
    with pytest.raises(ValueError):
        sel.min_arborescence([0, -1], -1, [])


def test_pair_model_is_optimal():
    for seed in range(5):
        x = noise(seed=seed)[:, :4]
        c = counts_from(x)
        family = all_itemsets(c, 4, 2)
        f = sel.TreeSearch(family, 4)
        w = {(i, j): f.best_tree(i, 0 if j < 0 else 1 << j)[0] for i in range(4) for j in range(-1, 4) if i != j}
        assert sel.pair_model(family, names(4)).cost() == pytest.approx(brute_tree(4, w))


@pytest.mark.parametrize("search", ["exhaustive", "greedy"])
@pytest.mark.parametrize("augment", ["direct", "ancestors"])
def test_selection_certificates(search, augment):
    for seed in range(4):
        c = counts_from(noise(seed=seed))
        family = mine_frequent(c, 5, 30, 4)
        singles = [(c.total, c.path(0, 0, i)[1]) for i in range(5)]
        m = sel.select_model(family, names(5), search, augment, singles=singles)
        assert sel.all_in_family(m, family)
        assert m.cost() <= independent_cost([x for _, x in singles], c.total) + 1e-9
        assert fixed_trees_model(c, names(5), m.trees).cost() == pytest.approx(m.cost())


def test_one_step_never_loses():
    """After a step, the best model with at most one more source each is no better than what the step found."""
    c = counts_from(noise()[:, :4])
    family = all_itemsets(c, 4, 4)
    f = sel.TreeSearch(family, 4)
    state = sel.SelectState(4)
    up = sel.select_step(state, f)
    got = sum(f.best_tree(i, 0 if up[i] < 0 else 1 << up[i])[0] for i in range(4))
    w = {(i, j): f.best_tree(i, 0 if j < 0 else 1 << j)[0] for i in range(4) for j in range(-1, 4) if i != j}
    assert got <= brute_tree(4, w) + 1e-9


def test_selection_ends_where_nodes_hang_on_marked_ones():
    """A chain in which later rounds attach unmarked items to items that are marked already."""
    c = counts_from(chain(n=3000, k=5))
    m = sel.select_model(all_itemsets(c, 5, 5), names(5))
    assert len(m.edges()) >= 4 and m.validate()


def test_infrequent_targets_stay_single():
    c = counts_from(noise())
    family = {k: v for k, v in all_itemsets(c, 5, 3).items() if not k & 1}
    singles = [(c.total, c.path(0, 0, i)[1]) for i in range(5)]
    m = sel.select_model(family, names(5), singles=singles)
    assert m.trees[0] == LEAF and m.counts[0, 0, 0] == singles[0]


def test_miners():
    x = noise()
    c = counts_from(x)
    f = mine_frequent(c, 5, 50, 5)
    for m in range(1, 32):
        s = int(x[:, [i for i in range(5) if m >> i & 1]].all(1).sum())
        assert (m in f) == (s >= 50) and f.get(m, s) == s
    low = mine_low_entropy(c, 5, 1.8, 3)
    assert all(m ^ 1 << i in low for m in low if m.bit_count() > 1 for i in range(5) if m >> i & 1)
    assert with_supports(c, [3])[3] == c.supports([3])[0]


def test_minimality_of_supports():
    """Two data sets that agree on all supports but one give different leaf tables."""
    a = np.array([[1, 1], [0, 0], [1, 0], [0, 1]], bool)
    b = np.array([[1, 0], [0, 1], [1, 0], [0, 1]], bool)
    ca, cb = counts_from(a), counts_from(b)
    assert ca.supports([1, 2]) == cb.supports([1, 2]) and ca.supports([3]) != cb.supports([3])
    assert sel.Supports(all_itemsets(ca, 2, 2)).count(3, 0) != sel.Supports(all_itemsets(cb, 2, 2)).count(3, 0)


@pytest.mark.parametrize("prune", [False, True])
def test_cover_baseline(prune):
    x = np.concatenate([np.tile([True, True, True, False], (60, 1)), np.random.default_rng(0).random((60, 4)) < 0.3])
    c = counts_from(x)
    v = cover_baseline(c, mine_frequent(c, 4, 2), prune)
    assert v.bits < v.start_bits and 0b0111 in v.table and not v.truncated
    assert sum(u * m.bit_count() for m, u in v.usage.items()) == int(x.sum())  # every one is covered once
    assert cover_baseline(c, mine_frequent(c, 4, 2), prune, 1).truncated


def test_masks_at_the_word_border():
    for k in (62, 63, 64, 70):
        x = np.random.default_rng(k).random((300, k)) < 0.3
        x[:, k - 1] = x[:, 0] ^ (np.random.default_rng(1).random(300) < 0.05)
        from codetrees.plans.counts import masks_to_words

        masks = [mask_of(np.flatnonzero(r).tolist()) for r in x]
        c = LocalCounts(masks_to_words(masks, k), np.ones(300, np.int64), k)
        assert c.supports([1 | 1 << (k - 1)]) == [int((x[:, 0] & x[:, k - 1]).sum())]
        m = grow_model(c, names(k))
        assert (k - 1, 0) in m.edges() or (0, k - 1) in m.edges()
