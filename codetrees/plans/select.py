"""Choosing itemsets from a downward-closed family: the best constrained tree, minimum directed spanning trees, and the
search for the order of attributes.

A family is a dict from item mask to support, always with 0 -> number of rows. Leaf counts come from supports alone, by
inclusion and exclusion, so nothing here reads data.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from codetrees.functions import codelen
from codetrees.plans.model import LEAF, Model, items_of, leaves, mask_of, sources_of

SCALE = 10**9


class Supports:
    """Leaf counts from supports: rows with all of pos and none of neg."""

    def __init__(self, family: dict[int, int]):
        self.family, self.memo = family, {}

    def count(self, pos: int, neg: int) -> int:
        if not neg:
            return self.family[pos]
        got = self.memo.get((pos, neg))
        if got is None:
            b = neg & -neg
            got = self.count(pos, neg ^ b) - self.count(pos | b, neg ^ b)
            self.memo[pos, neg] = got
        return got


class ScanCounts:
    """Leaf counts by looking at the data: rows split by every literal of the path. Same numbers as Supports."""

    def __init__(self, counts):
        self.counts = counts

    def count(self, pos: int, neg: int) -> int:
        return self.counts.path(pos, neg, 0)[0]


class TreeSearch:
    """Best trees under limits on sources and itemsets. search: "exhaustive" tries every root and both halves, keeping the
    leaf as an option; "greedy" grows top-down, one best split at a time. data: counts of the rows themselves, to be used
    in place of the family's supports."""

    def __init__(self, family: dict[int, int], k: int, search: str = "exhaustive", criterion: str = "refined", memo: bool = True, data=None):
        if search not in ("exhaustive", "greedy"):
            raise ValueError("search must be exhaustive or greedy")
        self.family, self.k, self.search, self.criterion, self.memo = family, k, search, criterion, memo
        self.supports, self.total = ScanCounts(data) if data is not None else Supports(family), family[0]
        self.split = codelen.split_cost(k)
        self.costs: dict[tuple[int, int], float] = {}

    def leaf(self, t: int, pos: int, neg: int) -> tuple[float, int, int]:
        if not self.family.get(1 << t) and 1 << t not in self.family:
            raise KeyError("the target is not in the family")
        n, n1 = self.supports.count(pos, neg), self.supports.count(pos | 1 << t, neg)
        cost = self.costs.get((n, n1))
        if cost is None:
            cost = self.costs[n, n1] = float(codelen.leaf_cost(n, n1, self.criterion, self.total))
        return cost, n, n1

    def best_tree(self, t: int, sources: int, single: tuple[int, int] | None = None):
        """(cost, tree) of target t with tests from `sources` only and every induced itemset in the family. A target that
        the family lacks keeps its single leaf; `single` then gives its (n, n1)."""
        if 1 << t not in self.family:
            n, n1 = single if single else (self.total, 0)
            return float(codelen.leaf_cost(n, n1, self.criterion, self.total)), LEAF
        if self.search == "greedy":
            return self._greedy(t, sources, 0, 0)
        return self._exhaustive(t, sources & ~(1 << t), {})

    def _legal(self, t: int, pos: int, neg: int, sources: int):
        path = pos | neg | 1 << t
        for b in items_of(sources & ~path):
            if path | 1 << b in self.family:
                yield b

    def _exhaustive(self, t: int, sources: int, known: dict):
        def solve(pos: int, neg: int):
            if self.memo and (pos, neg) in known:
                return known[pos, neg]
            cost, n, n1 = self.leaf(t, pos, neg)
            best = (cost, LEAF)
            floor = self.split + 2  # two leaves cost at least a bit each
            if cost > floor and not (self.criterion == "refined" and n1 in (0, n)):
                for b in self._legal(t, pos, neg, sources):
                    yes = solve(pos | 1 << b, neg)
                    if self.split + yes[0] + 1 >= best[0]:
                        continue
                    no = solve(pos, neg | 1 << b)
                    whole = self.split + yes[0] + no[0]
                    if whole < best[0] - 1e-12:
                        best = (whole, ("test", b, yes[1], no[1]))
            if self.memo:
                known[pos, neg] = best
            return best

        return solve(0, 0)

    def _greedy(self, t: int, sources: int, pos: int, neg: int):
        cost, n, n1 = self.leaf(t, pos, neg)
        if self.criterion == "refined" and n1 in (0, n):
            return cost, LEAF
        best = None
        for b in self._legal(t, pos, neg, sources & ~(1 << t)):
            whole = self.split + self.leaf(t, pos | 1 << b, neg)[0] + self.leaf(t, pos, neg | 1 << b)[0]
            if whole < cost - 1e-9 and (best is None or whole < best[0] - 1e-12):
                best = (whole, b)
        if best is None:
            return cost, LEAF
        b = best[1]
        yes, no = self._greedy(t, sources, pos | 1 << b, neg), self._greedy(t, sources, pos, neg | 1 << b)
        return self.split + yes[0] + no[0], ("test", b, yes[1], no[1])


def min_arborescence(nodes: list, sink, edges: list[tuple]) -> dict:
    """edges (from, to, weight): one out-edge per node, leading to the sink, of least total weight: {from: to}.

    Cycles of cheapest out-edges are contracted until there are none. Weights may be any numbers that add and compare."""
    best: dict = {}
    for e in edges:
        f, to, w = e[:3]
        if f != to and f != sink and (f not in best or w < best[f][1]):
            best[f] = (to, w)
    missing = [v for v in nodes if v != sink and v not in best]
    if missing:
        raise ValueError(f"no way out of {missing}")
    state: dict = {}
    cycle = None
    for v in nodes:
        path = []
        while v != sink and v not in state:
            state[v] = "open"
            path.append(v)
            v = best[v][0]
        if v != sink and state.get(v) == "open":
            cycle = path[path.index(v) :]
            break
        for u in path:
            state[u] = "done"
    if cycle is None:
        return {f: to for f, (to, _) in best.items() if f in set(nodes)}
    inside, merged = set(cycle), ("cycle", tuple(cycle))
    cheaper: dict = {}
    for f, to, w in (e[:3] for e in edges):
        if f == sink or f in inside and to in inside:
            continue
        a, b, c = (merged, to, w - best[f][1]) if f in inside else (f, merged if to in inside else to, w)
        if a != b and ((a, b) not in cheaper or c < cheaper[a, b][0]):
            cheaper[a, b] = (c, f, to)
    rest = [v for v in nodes if v not in inside] + [merged]
    got = min_arborescence(rest, sink, [(a, b, c) for (a, b), (c, _, _) in cheaper.items()])
    out = {}
    for a, b in got.items():
        _, f, to = cheaper[a, b]
        out[f] = to
    for v in cycle:
        out.setdefault(v, best[v][0])
    return out


@dataclass
class SelectState:
    """Sources of each attribute (masks), which are marked, and tree costs already known."""

    k: int
    sources: list[int] = field(default_factory=list)
    marked: set[int] = field(default_factory=set)
    known: dict = field(default_factory=dict)
    rounds: int = 0

    def __post_init__(self):
        self.sources = self.sources or [0] * self.k


def _tree(state: SelectState, search: TreeSearch, i: int, sources: int, singles):
    if (i, sources) not in state.known:
        state.known[i, sources] = search.best_tree(i, sources, singles[i] if singles else None)
    return state.known[i, sources]


def select_step(state: SelectState, search: TreeSearch, augment: str = "direct", singles=None, batch=None) -> dict:
    """One round: weigh the sink edge of every attribute and, for unmarked ones, the edges to every attribute that may
    join their sources; take the minimum directed spanning tree; mark those that hang on the sink; hand marked attributes
    to the sources of those that hang on them. Returns the tree {from: to}; the sink is -1."""
    k = state.k
    wanted = [(i, state.sources[i]) for i in range(k)]
    for i in range(k):
        if i not in state.marked:
            wanted += [(i, state.sources[i] | 1 << j) for j in range(k) if j != i and not state.sources[i] >> j & 1]
    missing = [w for w in wanted if w not in state.known]
    if batch and missing:
        state.known.update(batch(missing))
    edges = []
    for i in range(k):
        stay = _tree(state, search, i, state.sources[i], singles)[0]
        edges.append((i, -1, _weight(stay, False, i, -1, k)))
        if i in state.marked:
            continue
        for j in range(k):
            if j != i and not state.sources[i] >> j & 1:
                cost = _tree(state, search, i, state.sources[i] | 1 << j, singles)[0]
                if cost <= stay + 1e-12:
                    edges.append((i, j, _weight(min(cost, stay), True, i, j, k)))
    up = min_arborescence([*range(k), -1], -1, edges)
    state.marked |= {i for i in range(k) if up[i] == -1}
    for i in range(k):
        if i in state.marked:
            continue
        j = up[i]
        if augment == "ancestors":
            while j != -1:
                if j in state.marked:
                    state.sources[i] |= 1 << j
                j = up[j]
        elif j in state.marked:
            state.sources[i] |= 1 << j
    state.rounds += 1
    return up


def _weight(bits: float, to_node: bool, i: int, j: int, k: int) -> int:
    """Bits first (to 1e-9); ties prefer the sink, then lower indices. Whole numbers, so that sums are exact."""
    tie = (int(to_node) * (k + 2) + i + 1) * (k + 2) + j + 2
    return int(round(bits * SCALE)) * (k + 2) ** 4 + tie


def select_model(family: dict[int, int], names: list[str], search: str = "exhaustive", augment: str = "direct", criterion: str = "refined", singles=None, batch=None) -> Model:
    """Order and trees whose itemsets lie in the family. singles: (n, n1) of every item, for items the family lacks.
    batch: a function that solves many (target, sources) at once, e.g. on Spark executors."""
    k = len(names)
    finder = TreeSearch(family, k, search, criterion)
    state = SelectState(k)
    while len(state.marked) < k:
        select_step(state, finder, augment, singles, batch)
        if state.rounds > k + k * k:
            raise RuntimeError("the selection does not end")
    trees = [_tree(state, finder, i, state.sources[i], singles)[1] for i in range(k)]
    model = Model(list(names), family[0], trees, criterion=criterion).validate()
    for t, tree in enumerate(trees):
        for p, q in leaves(tree):
            pos, neg = mask_of(p), mask_of(q)
            if 1 << t in family:
                model.counts[t, pos, neg] = (finder.supports.count(pos, neg), finder.supports.count(pos | 1 << t, neg))
            else:
                model.counts[t, pos, neg] = singles[t] if singles else (family[0], 0)
    return model


def spark_batch(spark, family: dict[int, int], k: int, search: str, criterion: str, singles=None, at_least: int = 64):
    """Solve (target, sources) on executors; the family travels as a broadcast of checked size."""
    if len(family) > 10_000_000:
        raise ValueError("the family is too large to broadcast; raise its minimum support")
    shared = spark.sparkContext.broadcast((family, singles))

    def solve(wanted):
        if len(wanted) < at_least:
            finder = TreeSearch(family, k, search, criterion)
            return {w: finder.best_tree(*w, singles[w[0]] if singles else None) for w in wanted}
        rows = spark.createDataFrame([(n, i, str(s)) for n, (i, s) in enumerate(wanted)], "n int, i int, s string").repartition(min(len(wanted), 8 * spark.sparkContext.defaultParallelism))

        def run(batches):
            import json

            import pandas as pd

            fam, one = shared.value
            finder = TreeSearch(fam, k, search, criterion)
            for pdf in batches:
                got = [finder.best_tree(int(i), int(s), one[int(i)] if one else None) for i, s in zip(pdf["i"], pdf["s"], strict=True)]
                yield pd.DataFrame({"n": pdf["n"], "cost": [g[0] for g in got], "tree": [json.dumps(g[1]) for g in got]})

        import json

        fix = lambda t: LEAF if t[0] == "leaf" else ("test", t[1], fix(t[2]), fix(t[3]))
        return {wanted[r["n"]]: (r["cost"], fix(json.loads(r["tree"]))) for r in rows.mapInPandas(run, "n int, cost double, tree string").collect()}

    return solve


def pair_model(family: dict[int, int], names: list[str], criterion: str = "refined") -> Model:
    """The optimal model of a family of at most two items a set: one spanning tree. Works as one selection step."""
    if any(m.bit_count() > 2 for m in family):
        raise ValueError("pair_model takes itemsets of one or two items")
    k = len(names)
    finder, state = TreeSearch(family, k, criterion=criterion), SelectState(k)
    up = select_step(state, finder)
    trees = [finder.best_tree(i, 0 if up[i] == -1 else 1 << up[i])[1] for i in range(k)]
    model = Model(list(names), family[0], trees, criterion=criterion).validate()
    for t, tree in enumerate(trees):
        for p, q in leaves(tree):
            pos, neg = mask_of(p), mask_of(q)
            model.counts[t, pos, neg] = (finder.supports.count(pos, neg), finder.supports.count(pos | 1 << t, neg))
    return model


def all_in_family(model: Model, family: dict[int, int]) -> bool:
    """Whether every itemset of trees with tests lies in the family."""
    from codetrees.plans.model import itemsets_of_tree

    return all(s in family for t, tree in enumerate(model.trees) if sources_of(tree) for s in itemsets_of_tree(t, tree))
