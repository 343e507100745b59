"""Itemset families: supports, frequent and low-entropy miners, closure, itemsets of leaves, inclusion and exclusion."""

from __future__ import annotations

from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codetrees.operators.relational import contains_join, join_small
from codetrees.plans.counts import LocalCounts, _columns
from codetrees.plans.model import items_of

FAMILY_LIMIT = 10_000_000


def _extend(level: list[int]) -> list[int]:
    """Candidates one item larger, all of whose parts one item smaller are in the level."""
    have, out = set(level), set()
    by_head: dict[int, list[int]] = {}
    for m in level:
        top = 1 << (m.bit_length() - 1)
        by_head.setdefault(m ^ top, []).append(top)
    for head, tops in by_head.items():
        for a, b in combinations(sorted(tops), 2):
            x = head | a | b
            if all(x ^ (1 << i) in have for i in items_of(x)):
                out.add(x)
    return sorted(out)


def mine_frequent(counts, k: int, minsup: int, maxlen: int | None = None) -> dict[int, int]:
    """Itemsets with support of at least minsup rows, level by level: {mask: support}, with 0 -> number of rows."""
    family = {0: counts.total}
    level, size = [1 << i for i in range(k)], 1
    while level and (maxlen is None or size <= maxlen):
        found = {m: s for m, s in zip(level, counts.supports(level), strict=True) if s >= max(1, minsup)}
        family.update(found)
        if len(family) > FAMILY_LIMIT:
            raise ValueError("the family passes 10 million itemsets; raise minsup")
        level, size = _extend(sorted(found)), size + 1
    return family


def mine_lowest(counts, k: int, most: int) -> dict[int, int]:
    """All itemsets at the lowest support that has at most `most` of them, of any length. The threshold rises level by level
    to the lowest that the sets found so far allow; larger sets have no more support than their parts, so none is missed."""
    family, minsup = {}, 1
    level = [1 << i for i in range(k)]
    while level:
        family.update((m, s) for m, s in zip(level, counts.supports(level), strict=True) if s >= minsup)
        if len(family) > most:
            minsup = sorted(family.values(), reverse=True)[most] + 1
            family = {m: s for m, s in family.items() if s >= minsup}
        size = level[0].bit_count()
        level = _extend(sorted(m for m in family if m.bit_count() == size))
    return {0: counts.total, **family}


def mine_low_entropy(counts, k: int, max_bits: float, maxlen: int) -> dict[int, float]:
    """Itemsets whose joint entropy over all value patterns is at most max_bits; as entropy grows with the set, the family
    is downward closed: {mask: bits}."""
    out, level, size = {}, [1 << i for i in range(k)], 1
    while level and size <= maxlen:
        bits = _entropies(counts, level)
        keep = [m for m in level if bits[m] <= max_bits]
        out.update((m, bits[m]) for m in keep)
        level, size = _extend(keep), size + 1
    return out


def _entropies(counts, masks: list[int]) -> dict[int, float]:
    """Joint entropies by value patterns: on the driver from local counts, else by one job whose rows stay on executors."""
    if isinstance(counts, LocalCounts):
        return {m: _entropy(_cells(counts.words, m), counts.n, counts.total) for m in masks}
    total = counts.total

    def cells(batches):
        import pyarrow as pa

        for b in batches:
            words, n = _columns(b)
            for i, m in enumerate(masks):
                found, at = np.unique(_cells(words, m), return_inverse=True)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(found), i, np.int32)), pa.array(found), pa.array(np.bincount(at, n, len(found)).astype(np.int64))], names=["i", "cell", "c"])

    share = F.col("c") / F.lit(float(total))
    found = counts.ct.mapInArrow(cells, "i int, cell long, c long").groupBy("i", "cell").agg(F.sum("c").alias("c")).where("c > 0")
    got = {r["i"]: r["bits"] for r in found.groupBy("i").agg(F.sum(-share * F.log2(share)).alias("bits")).collect()}
    return {m: got.get(i, 0.0) for i, m in enumerate(masks)}


def _cells(words: np.ndarray, mask: int) -> np.ndarray:
    """The value pattern of each row on the items of a mask, as a number."""
    cells = np.zeros(len(words), np.int64)
    for j, i in enumerate(items_of(mask)):
        cells |= ((words[:, i // 63] >> np.uint64(i % 63)) & np.uint64(1)).astype(np.int64) << j
    return cells


def _entropy(cells: np.ndarray, n: np.ndarray, total: int) -> float:
    n = np.bincount(cells, n)
    n = n[n > 0]
    return float(-(n * np.log2(n / total)).sum() / total)


def all_itemsets(counts, k: int, maxlen: int = 2) -> dict[int, int]:
    """All itemsets of at most maxlen items with their supports, those that never occur included."""
    masks = [sum(1 << i for i in c) for size in range(1, maxlen + 1) for c in combinations(range(k), size)]
    return {0: counts.total, **dict(zip(masks, counts.supports(masks), strict=True))}


def with_supports(counts, masks) -> dict[int, int]:
    masks = sorted(set(masks) - {0})
    return {0: counts.total, **dict(zip(masks, counts.supports(masks), strict=True))}


def pick_minsup(counts, k: int, target_sets: int, maxlen: int) -> int:
    """The smallest power-of-two fraction of the rows whose family stays within target_sets."""
    s = counts.total // 2
    best = s
    while s >= 1 and len(mine_frequent(counts, k, s, maxlen)) <= target_sets:
        best, s = s, s // 2
    return best


def family_table(spark: SparkSession, family: dict[int, int]) -> DataFrame:
    """(mask, size, supp), without the empty set."""
    return spark.createDataFrame([(m, m.bit_count(), int(s)) for m, s in family.items() if m], "mask long, size int, supp long")


# ---- DataFrame operators


def itemset_supports(ct: DataFrame, sets: DataFrame) -> DataFrame:
    """Support of each mask of `sets` over compact rows: a containment join."""
    hit = contains_join(ct, sets.select("mask").distinct())
    found = hit.groupBy("mask").agg(F.sum("n").alias("supp"))
    return sets.select("mask").distinct().join(found, "mask", "left").select("mask", F.coalesce("supp", F.lit(0).cast("long")).alias("supp"))


def cooccurrence(ct: DataFrame, k: int) -> DataFrame:
    """(i, j, n): rows with both items, i <= j; item lists are exploded pairwise inside each compact row. The outer form
    keeps Catalyst from testing the lists for emptiness below the aggregation, on every row of the table."""
    present = F.expr(f"filter(sequence(0, {k - 1}), i -> (shiftright(m, i) & 1) = 1)")
    x = ct.select("n", present.alias("x")).select("n", "x", F.explode_outer("x").alias("i"))
    pairs = x.select("n", "i", F.explode_outer("x").alias("j")).where("i <= j")
    return pairs.groupBy("i", "j").agg(F.sum("n").alias("c"))


def fpgrowth(ct_baskets: DataFrame, min_support: float, maxlen: int) -> DataFrame:
    """Frequent sets by the built-in FP-growth over (items array): (items, freq) of at most maxlen items."""
    from pyspark.ml.fpm import FPGrowth

    got = FPGrowth(itemsCol="items", minSupport=min_support).fit(ct_baskets).freqItemsets
    return got.where(F.size("items") <= maxlen).select(F.array_sort("items").alias("items"), F.col("freq"))


def closure_violations(family: DataFrame) -> DataFrame:
    """Parts one item smaller that a family lacks: (mask, part)."""
    bits = F.expr("filter(sequence(0, 62), i -> (shiftright(mask, i) & 1) = 1)")
    parts = family.where("bit_count(mask) > 1").select("mask", F.explode(bits).alias("i")).select("mask", F.expr("mask - shiftleft(1L, i)").alias("part"))
    return parts.join(family.select(F.col("mask").alias("part")), "part", "left_anti").select("mask", "part")


def is_downward_closed(family: DataFrame) -> bool:
    return closure_violations(family).isEmpty()


def maximal_sets(family: DataFrame) -> DataFrame:
    """The sets of a family that lie in no larger set of it (each of at most 20 items)."""
    f = family.select("mask")
    below = f.select("mask", F.explode(subset_masks(F.col("mask"))).alias("part")).where("part <> mask").select(F.col("part").alias("mask")).distinct()
    return f.join(below, "mask", "left_anti")


def close_downward(family: DataFrame) -> DataFrame:
    """All non-empty parts of a family's itemsets (each of at most 20 items)."""
    return family.select(F.explode(subset_masks(F.col("mask"))).alias("mask")).where("mask <> 0").distinct()


def subset_masks(mask):
    """All sub-masks of a mask, as an array expression: the bits are folded one by one."""
    bits = F.filter(F.transform(F.sequence(F.lit(0), F.lit(62)), lambda i: F.call_function("shiftleft", F.lit(1).cast("long"), i)), lambda b: mask.bitwiseAND(b) != 0)
    return F.aggregate(bits, F.array(F.lit(0).cast("long")), lambda acc, b: F.concat(acc, F.transform(acc, lambda x: x.bitwiseOR(b))))


def leaf_sets(leaves: DataFrame) -> DataFrame:
    """(target, pos, neg masks) -> distinct induced itemsets (target, mask)."""
    both = leaves.select("target", "pos", F.explode(subset_masks(F.col("neg"))).alias("v"))
    t = F.expr("shiftleft(1L, target)")
    return both.select("target", F.explode(F.array(F.expr("pos | v"), F.expr("pos | v").bitwiseOR(t))).alias("mask")).distinct()


def leaf_counts_from_supports(leaves: DataFrame, supports: DataFrame) -> DataFrame:
    """Leaf counts (target, pos, neg, n, n1) by inclusion and exclusion over a support table (mask, supp)."""
    v = leaves.select("target", "pos", "neg", F.explode(subset_masks(F.col("neg"))).alias("v"))
    sign = F.expr("if(bit_count(v) % 2 = 0, 1, -1)")
    plain = F.expr("pos | v")
    probe = v.select("target", "pos", "neg", sign.alias("sign"), F.explode(F.array(F.struct(plain.alias("mask"), F.lit(0).alias("with_t")), F.struct(plain.bitwiseOR(F.expr("shiftleft(1L, target)")).alias("mask"), F.lit(1).alias("with_t")))).alias("q"))
    hit = probe.select("target", "pos", "neg", "sign", "q.mask", "q.with_t")
    hit = join_small(hit, supports, "mask")
    part = lambda w: F.sum(F.when(F.col("with_t") == w, F.col("sign") * F.col("supp")).otherwise(0)).cast("long")
    return hit.groupBy("target", "pos", "neg").agg(part(0).alias("n"), part(1).alias("n1"))


def coding_table(leaf_counts: DataFrame) -> DataFrame:
    """Share of ones at each leaf, from its counts."""
    return leaf_counts.withColumn("p1", F.try_divide(F.col("n1").cast("double"), F.col("n").cast("double")))


def dataset_stats(ct: DataFrame, k: int) -> DataFrame:
    """Rows, items, distinct rows and share of ones in %."""
    s = ct.agg(F.sum("n").alias("rows"), F.count("*").alias("distinct_rows"), F.sum(F.expr("bit_count(m) * n")).alias("ones"))
    return s.select("rows", F.lit(k).alias("items"), "distinct_rows", F.round(F.col("ones") * 100.0 / (F.col("rows") * k), 4).alias("pct_ones"))


def set_entropies(ct: DataFrame, sets: DataFrame) -> DataFrame:
    """Joint entropy in bits of each mask of `sets` over all value patterns."""
    cells = ct.crossJoin(F.broadcast(sets.select("mask"))).groupBy("mask", F.expr("m & mask").alias("cell")).agg(F.sum("n").alias("c"))
    total = ct.agg(F.sum("n").alias("total"))
    return cells.crossJoin(F.broadcast(total)).groupBy("mask").agg(F.sum(-(F.col("c") / F.col("total")) * F.log2(F.col("c") / F.col("total"))).alias("bits"))
