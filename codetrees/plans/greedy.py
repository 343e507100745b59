"""Greedy growth of a tree model from compact data.

All trees start as single leaves. Over all targets, leaves and items, the split that saves most bits is applied while any
saves, items may not repeat on a path, and the dependency graph must stay acyclic. The definition asks for a new search
over all candidates after each split; here every leaf's gains are computed once, as they depend only on the leaf's rows,
and the best that is allowed waits in a heap. Cycles only ever remove candidates, so popping the best, testing it then and
going on with the leaf's next one is exact. Counting by Spark runs in waves: the children of the best splits of the open
leaves that save most are counted together; on the driver the larger child is told by the smaller one and their parent.
"""

from __future__ import annotations

import heapq

import numpy as np

from codetrees.functions import codelen
from codetrees.plans.counts import Leaf
from codetrees.plans.model import LEAF, Closure, Model, mask_of, split_leaf, items_of

TIE = 9  # gains are compared when rounded to so many digits


def leaf_gains(counts, k: int, target: int, pos: int, neg: int, criterion: str = "refined") -> tuple[int, int, np.ndarray]:
    """(n, n1, gain in bits of splitting the leaf on each item); -inf for items that may not be tested there."""
    n, n1, nj, n1j = counts.path(pos, neg, target)
    gain = _gains([Leaf(n, n1, nj, n1j)], k, criterion, counts.total)[0]
    gain[[target, *items_of(pos | neg)]] = -np.inf
    return n, n1, gain


def _gains(some: list[Leaf], k: int, criterion: str, total: int) -> np.ndarray:
    """A row for each leaf: the gain of splitting it on each item."""
    n, n1 = np.array([[x.n] for x in some]), np.array([[x.n1] for x in some])
    nj, n1j = np.array([x.nj for x in some]), np.array([x.n1j for x in some])
    here, parts = codelen.leaf_cost(n, n1, criterion, total), codelen.leaf_cost(np.array([nj, n - nj]), np.array([n1j, n1 - n1j]), criterion, total)
    return here - codelen.split_cost(k) - parts[0] - parts[1]


def _can_gain(n: int, n1: int, cost: float, k: int, criterion: str) -> bool:
    """Exact prunes: a pure leaf under refined costs, and a leaf cheaper than any split's structure, cannot gain."""
    if criterion == "refined" and n1 in (0, n):
        return False
    return cost > 2 + codelen.split_cost(k)


def grow_model(counts, names: list[str], criterion: str = "refined", max_splits: int | None = None, max_depth: int | None = None, order: list[int] | None = None) -> Model:
    """Grow a model. order: a fixed order of items, each tree testing earlier ones only, in place of the cycle test."""
    k = len(names)
    model = Model(list(names), counts.total, [LEAF] * k, criterion=criterion)
    closure, heap = Closure(k), []
    place = {t: i for i, t in enumerate(order)} if order is not None else None
    opened: dict = {}  # (t, pos, neg) of leaves that wait in the heap: what is known of them, their other candidates
    splits: list[dict] = [{} for _ in range(k)]
    total = 0.0

    def can_gain(sizes: list[tuple[int, int]], depth: int) -> list[bool]:
        if max_depth is not None and depth >= max_depth:
            return [False] * len(sizes)
        costs = codelen.leaf_cost(*np.array(sizes).T, criterion, counts.total).tolist()
        return [_can_gain(*s, c, k, criterion) for s, c in zip(sizes, costs, strict=True)]

    def offer(key, leaf, rest) -> None:
        """Put the best allowed candidate of a leaf into the heap; those that would close a cycle now always will."""
        t = key[0]
        while rest:
            gain, j = rest.pop()
            if not closure.would_cycle(t, j):
                opened[key] = leaf, rest
                heapq.heappush(heap, (-round(gain, TIE), t, key[1:], j, gain))
                return

    def open_leaves(t: int, some: list) -> None:
        if not some:
            return
        for ((pos, neg), leaf), gain in zip(some, _gains([x for _, x in some], k, criterion, counts.total), strict=True):
            items = np.flatnonzero(gain > 10.0**-TIE)[::-1]
            items = items[np.argsort(gain[items], kind="stable")]  # the best last; of equal gains the least item
            saved = gain[items]
            apart = saved[1:] - saved[:-1]
            found = [x for x in zip(saved.tolist(), items.tolist(), strict=True) if not (pos | neg | 1 << t) >> x[1] & 1 and (place is None or place[x[1]] < place[t])]
            if ((apart > 0) & (apart < 2 * 10.0**-TIE)).any():
                found.sort(key=lambda x: (round(x[0], TIE), -x[1]))
            offer((t, pos, neg), leaf, found)

    counts.prefetch([(0, 0)])
    for t in range(k):
        leaf = counts.root(t)
        model.counts[t, 0, 0] = leaf.n, leaf.n1
        if can_gain([(leaf.n, leaf.n1)], 0)[0]:
            open_leaves(t, [((0, 0), leaf)])
        total += float(codelen.leaf_cost(leaf.n, leaf.n1, criterion, counts.total))

    while heap and (max_splits is None or len(model.trace) < max_splits):
        _, t, (pos, neg), j, gain = heapq.heappop(heap)
        leaf, rest = opened.pop((t, pos, neg))
        if place is None and closure.would_cycle(t, j):
            offer((t, pos, neg), leaf, rest)
            continue
        wave = [(pos | 1 << j, neg), (pos, neg | 1 << j)]
        sizes = [leaf.child(j, True), leaf.child(j, False)]
        want = can_gain(sizes, (pos | neg).bit_count() + 1)
        need = [w for w, x in zip(wave, want, strict=True) if x]
        if getattr(counts, "kept", None) is not None and any(w not in counts.kept for w in need):
            counts.prefetch(need + _ahead(heap, opened, closure, place, counts))
        closure.add(t, j)
        total -= gain
        splits[t][pos, neg] = j
        del model.counts[t, pos, neg]
        model.trace.append((t, pos, neg, j, gain, total))
        for (p, q), size in zip(wave, sizes, strict=True):
            model.counts[t, p, q] = size
        parts = counts.split(leaf, t, j, pos, neg, want)
        open_leaves(t, [(w, x) for w, x in zip(wave, parts, strict=True) if x is not None])
    model.trees = [_tree(x) for x in splits]
    return model


def _tree(splits: dict, pos: int = 0, neg: int = 0):
    """The tree of the splits {(pos, neg): item}."""
    j = splits.get((pos, neg))
    return LEAF if j is None else ("test", j, _tree(splits, pos | 1 << j, neg), _tree(splits, pos, neg | 1 << j))


def _ahead(heap, opened, closure, place, counts) -> list[tuple[int, int]]:
    """Children, not counted yet, of the best allowed split of the open leaves that save most: likely to be asked for soon."""
    out: dict = {}
    for _, t, (pos, neg), j, _ in sorted(heap):
        if len(out) >= counts.ahead:
            break
        if place is None:
            j = next((i for i in (j, *(x[1] for x in reversed(opened[t, pos, neg][1]))) if not closure.would_cycle(t, i)), None)
        if j is not None:
            out |= {p: None for p in ((pos | 1 << j, neg), (pos, neg | 1 << j)) if p not in counts.kept}
    return list(out)


def grow_naively(counts, names: list[str], criterion: str = "refined", max_splits: int | None = None) -> Model:
    """The definition as it stands, for tests: look at every candidate after every split."""
    k = len(names)
    model, closure = Model(list(names), counts.total, [LEAF] * k, criterion=criterion), Closure(k)
    total = 0.0
    for t in range(k):
        model.counts[t, 0, 0] = counts.path(0, 0, t)[:2]
        total += float(codelen.leaf_cost(*model.counts[t, 0, 0], criterion, counts.total))
    while max_splits is None or len(model.trace) < max_splits:
        best = None
        for t, pos, neg in model.counts:
            gain = leaf_gains(counts, k, t, pos, neg, criterion)[2]
            for j in range(k):
                if gain[j] > 10.0**-TIE and not closure.would_cycle(t, j):
                    key = (-round(float(gain[j]), TIE), t, (pos, neg), j, float(gain[j]))
                    best = key if best is None or key < best else best
        if best is None:
            break
        _, t, (pos, neg), j, gain = best
        closure.add(t, j)
        total -= gain
        model.trees[t] = split_leaf(model.trees[t], frozenset(items_of(pos)), frozenset(items_of(neg)), j)
        del model.counts[t, pos, neg]
        model.trace.append((t, pos, neg, j, gain, total))
        for p, q in ((pos | 1 << j, neg), (pos, neg | 1 << j)):
            model.counts[t, p, q] = counts.path(p, q, t)[:2]
    return model


def fixed_trees_model(counts, names: list[str], trees: list, criterion: str = "refined") -> Model:
    """A model of given trees with leaf counts taken from the data."""
    from codetrees.plans.model import leaves

    model = Model(list(names), counts.total, list(trees), criterion=criterion).validate()
    paths = [(t, mask_of(p), mask_of(n)) for t, tree in enumerate(trees) for p, n in leaves(tree)]
    counts.prefetch([(p, n) for _, p, n in paths])
    for t, p, n in paths:
        model.counts[t, p, n] = counts.path(p, n, t)[:2]
    return model
