"""Applying models to rows: routing to leaves, code lengths, lossless residuals, classification by code length.

Rows carry their items in `m`, a mask of at most 63 items, or in `w`, an array of such masks for any number of items.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from codetrees.plans.counts import bit_matrix, counts_of, stored, words_of
from codetrees.plans.greedy import grow_model
from codetrees.plans.model import LEAF, Model, mask_of

SMOOTHING = ("ml", "laplace", "kt")


def symbol_bits(n: int, nv: int, smoothing: str = "kt") -> float:
    """Bits of a value seen nv times among n at its leaf; ml gives inf for values never seen."""
    a, b = {"ml": (0.0, 0.0), "laplace": (1.0, 2.0), "kt": (0.5, 1.0)}[smoothing]
    p = (nv + a) / (n + b) if n + b > 0 else 0.5
    return -math.log2(p) if p > 0 else math.inf


def items_column(df: DataFrame) -> str:
    """The column that holds the items: m, or w where there is no m."""
    return "m" if "m" in df.columns else "w"


def has_item(i: int, column: str = "m") -> str:
    """SQL test for an item."""
    return f"m & {1 << i} <> 0" if column == "m" else f"w[{i // 63}] & {1 << i % 63} <> 0"


def _case(tree, leaf, column: str = "m", pos=frozenset(), neg=frozenset()) -> str:
    """Nested CASE over the items; leaf(pos, neg) gives the SQL of a leaf."""
    if tree == LEAF:
        return leaf(mask_of(pos), mask_of(neg))
    _, a, p, q = tree
    return f"CASE WHEN {has_item(a, column)} THEN {_case(p, leaf, column, pos | {a}, neg)} ELSE {_case(q, leaf, column, pos, neg | {a})} END"


def _number(x: float) -> str:
    return "cast('Infinity' AS double)" if math.isinf(x) else f"{x!r}D"


def leaf_of_expr(model: Model, target: int, column: str = "m") -> Column:
    """Number of the leaf (in path order, positive first) that a row reaches in the target's tree."""
    place = {}

    def leaf(pos, neg):
        return str(place.setdefault((pos, neg), len(place)))

    return F.expr(_case(model.trees[target], leaf, column)).cast("int")


def code_length_expr(model: Model, smoothing: str = "kt", column: str = "m") -> Column:
    """Bits of a row under the model: one projection of nested CASEs, no shuffle."""
    parts = []
    for t, tree in enumerate(model.trees):

        def leaf(pos, neg, t=t):
            n, n1 = model.counts[t, pos, neg]
            return f"CASE WHEN {has_item(t, column)} THEN {_number(symbol_bits(n, n1, smoothing))} ELSE {_number(symbol_bits(n, n - n1, smoothing))} END"

        parts.append(_case(tree, leaf, column))
    return F.expr(" + ".join(f"({p})" for p in parts))


class RowScorer:
    """Vectorised routing in numpy, for models too large for one generated method: rows go down a tree together, one test
    a step, so that a row costs as many tests as it meets, not as many as there are leaves."""

    def __init__(self, model: Model, smoothing: str = "kt"):
        self.k, self.order = model.k, model.order()
        self.trees = [self._flat(model, t, smoothing) for t in range(model.k)]

    @staticmethod
    def _flat(model: Model, t: int, smoothing: str) -> tuple:
        """(nodes, leaves): item, places of the nodes with and without it, or -1 and the number of the leaf; bits of a one
        and of a zero, and the majority, of the leaves in path order."""
        nodes, leaves, todo = [], [], [(model.trees[t], 0, 0, None)]
        while todo:
            tree, pos, neg, above = todo.pop()
            if above is not None:
                nodes[above[0]][above[1]] = len(nodes)
            if tree == LEAF:
                n, n1 = model.counts[t, pos, neg]
                nodes.append([-1, len(leaves), 0])
                leaves.append((symbol_bits(n, n1, smoothing), symbol_bits(n, n - n1, smoothing), 2 * n1 > n))
            else:
                _, a, p, q = tree
                todo += [(q, pos, neg | 1 << a, (len(nodes), 2)), (p, pos | 1 << a, neg, (len(nodes), 1))]
                nodes.append([a, 0, 0])
        one, zero, major = zip(*leaves, strict=True)
        return np.array(nodes, np.int32).T.copy(), (np.array(one), np.array(zero), np.array(major, bool))

    def leaf(self, x: np.ndarray, t: int) -> np.ndarray:
        """Number of the leaf that each row reaches."""
        item, yes, no = self.trees[t][0]
        out, rows = np.zeros(len(x), np.int32), np.arange(len(x))
        at = np.zeros(len(x), np.int32)
        while len(rows):
            test = item[at]
            ends = test < 0
            if ends.any():
                out[rows[ends]] = yes[at[ends]]
                rows, at, test = rows[~ends], at[~ends], test[~ends]
            at = np.where(x[rows, test], yes[at], no[at])
        return out

    def bits(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros(len(x))
        for t, (_, (one, zero, _)) in enumerate(self.trees):
            leaf = self.leaf(x, t)
            out += np.where(x[:, t], one[leaf], zero[leaf])
        return out

    def tally(self, x: np.ndarray, n: np.ndarray) -> np.ndarray:
        """(target, leaf, n, n1) of the leaves that weighted rows reach, leaves numbered in path order."""
        out = []
        for t in range(self.k):
            found, leaf = np.unique(self.leaf(x, t), return_inverse=True)
            sums = np.zeros((2, len(found)), np.int64)
            np.add.at(sums[0], leaf, n)
            np.add.at(sums[1], leaf, n * x[:, t])
            out.append(np.stack([np.full(len(found), t), found, *sums], 1))
        return np.concatenate(out).astype(np.int64).reshape(-1, 4)

    def guess(self, x: np.ndarray, t: int) -> np.ndarray:
        """Majority value of the target at each row's leaf."""
        return self.trees[t][1][2][self.leaf(x, t)]

    def residuals(self, x: np.ndarray) -> np.ndarray:
        return np.stack([x[:, t] ^ self.guess(x, t) for t in range(self.k)], 1)

    def restore(self, r: np.ndarray) -> np.ndarray:
        x = np.zeros_like(r)
        for t in self.order:
            x[:, t] = r[:, t] ^ self.guess(x, t)
        return x


def code_length(packed: DataFrame, model: Model, smoothing: str = "kt", most_leaves: int = 200) -> DataFrame:
    """packed plus `bits`. Small models compile to CASEs; larger ones run in numpy on Arrow batches."""
    at = items_column(packed)
    if sum(1 for _ in model.leaf_rows()) <= most_leaves:
        return packed.withColumn("bits", code_length_expr(model, smoothing, at))
    scorer = RowScorer(model, smoothing)

    def run(batches):
        import pyarrow as pa

        for b in batches:
            x = bit_matrix(words_of(b.column(at)), scorer.k).astype(bool)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(scorer.bits(x))], names=[*b.schema.names, "bits"])

    return packed.mapInArrow(run, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in packed.schema) + ", bits double")


def route(packed: DataFrame, model: Model) -> DataFrame:
    """(key, target, leaf): the leaf each row reaches in every tree."""
    each = F.array(*[F.struct(F.lit(t).alias("target"), leaf_of_expr(model, t, items_column(packed)).alias("leaf")) for t in range(model.k)])
    return packed.select("key", F.explode(each).alias("x")).select("key", "x.target", "x.leaf")


def leaf_counts(ct: DataFrame, model: Model, most_leaves: int = 100) -> DataFrame:
    """(target, leaf, n, n1) of all leaves by one pass over distinct rows. Beyond most_leaves, partitions are tallied in
    numpy, so that no row is multiplied by the number of trees and only a line a leaf and batch is shuffled."""
    at = items_column(ct)
    if sum(1 for _ in model.leaf_rows()) > most_leaves:
        scorer = RowScorer(model)

        def run(batches):
            import pyarrow as pa

            for b in batches:
                got = scorer.tally(bit_matrix(words_of(b.column(at)), scorer.k).astype(bool), b.column("n").to_numpy())
                yield pa.RecordBatch.from_arrays([pa.array(got[:, 0].astype(np.int32)), pa.array(got[:, 1].astype(np.int32)), pa.array(got[:, 2]), pa.array(got[:, 3])], names=["target", "leaf", "n", "n1"])

        got = ct.select(at, "n").mapInArrow(run, "target int, leaf int, n long, n1 long")
        return got.groupBy("target", "leaf").agg(F.sum("n").alias("n"), F.sum("n1").alias("n1"))
    each = F.array(*[F.struct(F.lit(t).alias("target"), leaf_of_expr(model, t, at).alias("leaf"), F.expr(f"cast({has_item(t, at)} AS long)").alias("one")) for t in range(model.k)])
    x = ct.select("n", F.explode(each).alias("x"))
    return x.groupBy("x.target", "x.leaf").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("x.one")).alias("n1"))


def _masks(x: np.ndarray) -> np.ndarray:
    return (x.astype(np.int64) << np.arange(x.shape[1])).sum(1)


def _mapped(packed: DataFrame, model: Model, what: str) -> DataFrame:
    scorer, at = RowScorer(model), items_column(packed)

    def run(batches):
        import pyarrow as pa

        for b in batches:
            x = bit_matrix(words_of(b.column(at)), scorer.k).astype(bool)
            out = getattr(scorer, what)(x)
            if at == "m":
                got = pa.array(_masks(out))
            else:
                words = np.stack([_masks(out[:, i : i + 63]) for i in range(0, scorer.k, 63)], 1)
                got = pa.ListArray.from_arrays(pa.array(np.arange(len(out) + 1, dtype=np.int32) * words.shape[1]), pa.array(words.ravel()))
            yield pa.RecordBatch.from_arrays([b.column("key"), got], names=["key", at])

    return packed.select("key", at).mapInArrow(run, f"key {packed.schema['key'].dataType.simpleString()}, {at} {'long' if at == 'm' else 'array<long>'}")


def to_residuals(packed: DataFrame, model: Model) -> DataFrame:
    """Rows as differences from each leaf's majority."""
    return _mapped(packed, model, "residuals")


def from_residuals(residuals: DataFrame, model: Model) -> DataFrame:
    """Rows restored in sending order: each tree tests only what is restored already."""
    return _mapped(residuals, model, "restore")


# ---- classification


def split_bucket(key: Column) -> Column:
    """True for the hold-out, about a tenth: by md5, so that any engine finds the same rows."""
    return F.substring(F.md5(F.concat(F.lit("split-"), key.cast("string")).cast("binary")), 1, 2) < "1a"


def fit_class_models(train: DataFrame, names: list[str], criterion: str = "refined", fit=None) -> dict:
    """train: (label, m) or (label, w) -> {label: model}. One aggregation, stored, serves all classes."""
    at = items_column(train)
    ct = stored(train.groupBy("label", at).agg(F.count("*").alias("n")), "classes")
    labels = sorted(r[0] for r in ct.select("label").distinct().collect())
    fit = fit or (lambda counts: grow_model(counts, names, criterion))
    return {c: fit(counts_of(ct.where(F.col("label") == c).select(at, "n"), len(names), made=True)) for c in labels}


def classify_by_code_length(rows: DataFrame, models: dict, smoothing: str = "kt", prior: bool = False) -> DataFrame:
    """rows (with m or w) plus `pred`: the label whose model needs fewest bits; ties go to the least label."""
    total = sum(m.total for m in models.values())
    out, cols = rows, []
    for i, (label, model) in enumerate(sorted(models.items())):
        out = code_length(out, model, smoothing, 200 // len(models)).withColumnRenamed("bits", f"__b{i}")  # one stage scores all
        extra = -math.log2(model.total / total) if prior else 0.0
        cols.append(F.struct((F.col(f"__b{i}") + F.lit(extra)).alias("bits"), F.lit(i).alias("i"), F.lit(label).alias("label")))
    out = out.withColumn("pred", F.array_min(F.array(*cols))["label"])
    return out.drop(*[f"__b{i}" for i in range(len(models))])


def accuracy(scored: DataFrame) -> DataFrame:
    return scored.agg(F.count("*").alias("rows"), F.sum((F.col("pred") == F.col("label")).cast("long")).alias("right"), F.round(F.avg((F.col("pred") == F.col("label")).cast("double")), 6).alias("accuracy"))


def confusion(scored: DataFrame) -> DataFrame:
    return scored.groupBy("label").pivot("pred").count().na.fill(0)


def majority_accuracy(train: DataFrame, test: DataFrame) -> DataFrame:
    """Accuracy of always saying the commonest training label (ties: the least)."""
    top = train.groupBy("label").count().orderBy(F.desc("count"), "label").limit(1).select(F.col("label").alias("pred"))
    return accuracy(test.crossJoin(F.broadcast(top)))
