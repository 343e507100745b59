"""Trees, tree models, their dependency graph and costs; conversion to and from flat tables.

A tree is a tuple: ("leaf",) or ("test", item, positive, negative). Items are 0-based indices into an ordered catalogue.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codetrees.functions import codelen

LEAF = ("leaf",)
KEPT_SPANS = 200_000  # of the counts that count_between remembers, some 50 MB


def join_trees(item: int, positive, negative):
    """A test on item with two subtrees that do not use it."""
    if item in sources_of(positive) | sources_of(negative):
        raise ValueError("an item may be tested once on a path")
    return ("test", item, positive, negative)


def sources_of(tree) -> set[int]:
    """Items that a tree tests."""
    return set() if tree == LEAF else {tree[1]} | sources_of(tree[2]) | sources_of(tree[3])


def leaves(tree, pos: frozenset = frozenset(), neg: frozenset = frozenset()):
    """(pos, neg) of every leaf, positive branches first."""
    if tree == LEAF:
        yield pos, neg
    else:
        yield from leaves(tree[2], pos | {tree[1]}, neg)
        yield from leaves(tree[3], pos, neg | {tree[1]})


def split_leaf(tree, pos: frozenset, neg: frozenset, item: int):
    """The tree with the leaf at (pos, neg) replaced by a test on item."""
    if tree == LEAF:
        if pos or neg:
            raise ValueError("no such leaf")
        return ("test", item, LEAF, LEAF)
    _, a, p, n = tree
    if a == item:
        raise ValueError("an item may be tested once on a path")
    if a in pos:
        return ("test", a, split_leaf(p, pos - {a}, neg, item), n)
    if a in neg:
        return ("test", a, p, split_leaf(n, pos, neg - {a}, item))
    raise ValueError("no such leaf")


def mask_of(items) -> int:
    return sum(1 << i for i in items)


def items_of(mask: int) -> list[int]:
    out, i = [], 0
    while mask:
        if mask & 1:
            out.append(i)
        mask >>= 1
        i += 1
    return out


class Closure:
    """Reachability of a growing directed graph as bit sets."""

    def __init__(self, k: int):
        self.edges = [0] * k
        self.reach = [0] * k

    def would_cycle(self, src: int, dst: int) -> bool:
        """Whether an edge from src to dst closes a cycle. An edge that is there already does not; a loop does."""
        if src == dst:
            return True
        return not self.edges[src] >> dst & 1 and bool(self.reach[dst] >> src & 1)

    def add(self, src: int, dst: int) -> None:
        if self.would_cycle(src, dst):
            raise ValueError("the edge closes a cycle")
        if self.edges[src] >> dst & 1:
            return
        self.edges[src] |= 1 << dst
        new = self.reach[dst] | 1 << dst
        for v in range(len(self.reach)):
            if v == src or self.reach[v] >> src & 1:
                self.reach[v] |= new


def topological_order(k: int, edges) -> list[int] | None:
    """Nodes so that every edge's destination comes before its source; None if there is a cycle. Least index first."""
    need = {i: set() for i in range(k)}
    for s, d in edges:
        need[s].add(d)
    order, placed = [], set()
    while len(order) < k:
        ready = [i for i in range(k) if i not in placed and need[i] <= placed]
        if not ready:
            return None
        order.append(ready[0])
        placed.add(ready[0])
    return order


@dataclass
class Model:
    """One tree per item. counts: (target, pos mask, neg mask) -> (n, n1) of every leaf, where known."""

    names: list[str]
    total: int
    trees: list
    counts: dict = field(default_factory=dict)
    criterion: str = "refined"
    trace: list = field(default_factory=list)

    @property
    def k(self) -> int:
        return len(self.names)

    def edges(self) -> list[tuple[int, int]]:
        return [(t, s) for t, tree in enumerate(self.trees) for s in sorted(sources_of(tree))]

    def order(self) -> list[int]:
        got = topological_order(self.k, self.edges())
        if got is None:
            raise ValueError("the trees depend on each other in a cycle")
        return got

    def validate(self) -> Model:
        for t, tree in enumerate(self.trees):
            if t in sources_of(tree):
                raise ValueError("a tree tests its own target")
        self.order()
        return self

    def leaf_rows(self):
        for t, tree in enumerate(self.trees):
            for pos, neg in leaves(tree):
                n, n1 = self.counts.get((t, mask_of(pos), mask_of(neg)), (None, None))
                yield t, pos, neg, n, n1

    def data_bits(self) -> float:
        return float(sum(codelen.data_bits(n, n1) for *_, n, n1 in self.leaf_rows()))

    def tree_cost(self, target: int) -> float:
        rows = [r for r in self.leaf_rows() if r[0] == target]
        cost = sum(float(codelen.leaf_cost(n, n1, self.criterion, self.total)) for *_, n, n1 in rows)
        return cost + (len(rows) - 1) * codelen.split_cost(self.k)

    def cost(self) -> float:
        """Sum of the tree costs; all leaves are walked once."""
        rows = list(self.leaf_rows())
        bits: list[list[float]] = [[] for _ in range(self.k)]
        for (t, *_), b in zip(rows, codelen.leaf_cost(*zip(*((n, n1) for *_, n, n1 in rows), strict=True), self.criterion, self.total).tolist() if rows else [], strict=True):
            bits[t].append(b)
        return sum(sum(x) + (len(x) - 1) * codelen.split_cost(self.k) for x in bits)

    def itemsets(self, include_empty: bool = False, max_neg: int = 22) -> set[int]:
        """Masks of all itemsets that the leaves induce: pos with any part of neg, with and without the target."""
        out: set[int] = set()
        for t, tree in enumerate(self.trees):
            out |= itemsets_of_tree(t, tree, max_neg)
        return out if include_empty else out - {0}

    def count_itemsets(self, include_empty: bool = False) -> int:
        """Number of induced itemsets, without listing them: leaves of any number of tests."""
        spans = {(p, p | n | 1 << t) for t, tree in enumerate(self.trees) for p, n in ((mask_of(a), mask_of(b)) for a, b in leaves(tree))}
        return count_between(spans) - (not include_empty and any(low == 0 for low, _ in spans))

    def to_json(self) -> str:
        return json.dumps({"names": self.names, "total": self.total, "trees": self.trees, "criterion": self.criterion, "counts": [[*k, *v] for k, v in self.counts.items()], "trace": self.trace})

    @classmethod
    def from_json(cls, text: str) -> Model:
        d = json.loads(text)
        fix = lambda t: LEAF if t[0] == "leaf" else ("test", t[1], fix(t[2]), fix(t[3]))
        return cls(d["names"], d["total"], [fix(t) for t in d["trees"]], {(a, p, n): (x, y) for a, p, n, x, y in d["counts"]}, d["criterion"], [tuple(t) for t in d["trace"]])

    # ---- tables

    def nodes_table(self, spark: SparkSession, model_id: str = "model") -> DataFrame:
        """One row per node of every tree."""
        rows = []
        for t, tree in enumerate(self.trees):
            todo, nid = [(tree, None, None, frozenset(), frozenset())], 0
            while todo:
                node, parent, branch, pos, neg = todo.pop()
                leaf = node == LEAF
                n, n1 = self.counts.get((t, mask_of(pos), mask_of(neg)), (None, None)) if leaf else (None, None)
                bits = (float(codelen.complexity(n, self.criterion, self.total)), float(codelen.data_bits(n, n1))) if leaf and n is not None else (0.0, 0.0)
                rows.append((model_id, t, nid, parent, branch, None if leaf else node[1], len(pos) + len(neg), sorted(pos), sorted(neg), n, n1, 1.0 if leaf else codelen.split_cost(self.k), *bits))
                if not leaf:
                    todo.append((node[3], nid, 0, pos, neg | {node[1]}))
                    todo.append((node[2], nid, 1, pos | {node[1]}, neg))
                nid += 1
        return spark.createDataFrame(rows, NODES)

    def itemsets_table(self, spark: SparkSession, include_empty: bool = False) -> DataFrame:
        """One row per induced itemset: mask (K <= 63 only), items, names, size."""
        rows = [(m if self.k <= 63 else None, items_of(m), [self.names[i] for i in items_of(m)], len(items_of(m))) for m in sorted(self.itemsets(include_empty))]
        return spark.createDataFrame(rows, "mask long, items array<int>, names array<string>, size int")

    def edges_table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(s, d, self.names[s], self.names[d]) for s, d in self.edges()], "src int, dst int, src_name string, dst_name string")

    def trace_table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(i + 1, t, sorted(items_of(p)), sorted(items_of(n)), s, g, c) for i, (t, p, n, s, g, c) in enumerate(self.trace)], "step int, target int, leaf_pos array<int>, leaf_neg array<int>, split int, gain double, total double")

    def leaves_table(self, spark: SparkSession) -> DataFrame:
        rows = [(t, mask_of(p), mask_of(n), a, b) for t, p, n, a, b in self.leaf_rows()]
        return spark.createDataFrame(rows, "target int, pos long, neg long, n long, n1 long")

    def signatures(self) -> list[list[str]]:
        """Each tree that tests anything, shown as one association: its target and sources."""
        return [[self.names[t], *(self.names[s] for s in sorted(sources_of(tree)))] for t, tree in enumerate(self.trees) if tree != LEAF]

    def packed_by(self, item: str) -> list[str]:
        """Targets whose trees test the item."""
        i = self.names.index(item)
        return [self.names[t] for t, s in self.edges() if s == i]

    def explain(self, target: int) -> str:
        """A readable tree."""

        def lines(node, pad, pos, neg):
            if node == LEAF:
                n, n1 = self.counts.get((target, mask_of(pos), mask_of(neg)), (None, None))
                yield f"{pad}P({self.names[target]}) = {n1 / n:.3f} of {n}" if n else f"{pad}no rows"
            else:
                yield f"{pad}{self.names[node[1]]}?"
                yield f"{pad}  yes"
                yield from lines(node[2], pad + "    ", pos | {node[1]}, neg)
                yield f"{pad}  no"
                yield from lines(node[3], pad + "    ", pos, neg | {node[1]})

        return "\n".join(lines(self.trees[target], "", frozenset(), frozenset()))

NODES = "model_id string, target int, node_id int, parent_id int, branch int, split_item int, depth int, pos array<int>, neg array<int>, n long, n1 long, bits_struct double, bits_complexity double, bits_data double"


def itemsets_of_leaf(target: int, pos: int, neg: int, max_neg: int = 22) -> set[int]:
    """pos with any part of neg, with and without the target."""
    if neg.bit_count() > max_neg:
        raise ValueError(f"a leaf with {neg.bit_count()} negative tests induces too many itemsets to list")
    out, sub = set(), neg
    while True:
        out.add(pos | sub)
        out.add(pos | sub | 1 << target)
        if not sub:
            return out
        sub = (sub - 1) & neg


def widest(spans) -> frozenset[tuple[int, int]]:
    """The spans (low, high) that lie in no other one."""
    out: list[tuple[int, int]] = []
    for low, high in sorted(spans, key=lambda s: (s[0].bit_count() - s[1].bit_count(), s)):
        if not any(not a & ~low and not high & ~b for a, b in out):
            out.append((low, high))
    return frozenset(out)


def count_between(spans: set[tuple[int, int]], most: int = KEPT_SPANS) -> int:
    """Number of sets that lie between low and high (as masks, both included) of any span. Spans inside others are left
    out, items that decide most spans are decided one by one, and items that no span asks for double the count. Counts of
    at most `most` spans in all are remembered."""
    known: dict[frozenset, int] = {}
    held = 0

    def count(some: frozenset) -> int:
        nonlocal held
        if not some:
            return 0
        if len(some) == 1:
            ((low, high),) = some
            return 1 << (high & ~low).bit_count()
        if some in known:
            return known[some]
        lows = highs = 0
        fixed, free = -1, -1
        for low, high in some:
            lows, highs, fixed, free = lows | low, highs | high, fixed & low, free & high
        free &= ~lows
        if (0, highs) in some:
            return 1 << highs.bit_count()
        if free or fixed:
            drop = ~(free | fixed)
            return count(frozenset((low & drop, high & drop) for low, high in some)) << free.bit_count()
        item = 1 << max(items_of(highs), key=lambda i: sum((low >> i & 1) + (~high >> i & 1) for low, high in some))
        out = count(widest({(low & ~item, high & ~item) for low, high in some if high & item}))
        out += count(widest({(low, high & ~item) for low, high in some if not low & item}))
        if held + len(some) > most:
            known.clear()
            held = 0
        known[some] = out
        held += len(some)
        return out

    return count(widest(spans))


def itemsets_of_tree(target: int, tree, max_neg: int = 22) -> set[int]:
    out: set[int] = set()
    for pos, neg in leaves(tree):
        out |= itemsets_of_leaf(target, mask_of(pos), mask_of(neg), max_neg)
    return out


def independent_cost(singles, total: int, criterion: str = "refined") -> float:
    """Cost when every tree is a single leaf; singles: number of ones of each item."""
    return float(sum(codelen.leaf_cost(total, n1, criterion, total) for n1 in singles))


def independent_model(names: list[str], singles, total: int, criterion: str = "refined") -> Model:
    return Model(list(names), total, [LEAF] * len(names), {(i, 0, 0): (total, int(n1)) for i, n1 in enumerate(singles)}, criterion)


def save_model(model: Model, spark: SparkSession, path: str, model_id: str = "model") -> None:
    """One partition per model id: the model as JSON."""
    spark.createDataFrame([(model_id, model.to_json())], "model_id string, model string").write.mode("append").partitionBy("model_id").parquet(path)


def load_model(spark: SparkSession, path: str, model_id: str = "model") -> Model:
    row = spark.read.parquet(path).where(F.col("model_id") == model_id).first()
    return Model.from_json(row["model"])
