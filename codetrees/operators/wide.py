"""Statistics of rows with any number of items, as arrays of masks: distinct rows are (w, n)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from codetrees.functions import codelen
from codetrees.operators.relational import contains_join

WORD_BITS = 63


def items_in(column: str = "w") -> Column:
    """Items of a word array, ascending."""
    return F.expr(f"flatten(transform({column}, (x, j) -> transform(filter(sequence(0, {WORD_BITS - 1}), i -> (shiftright(x, i) & 1) = 1), i -> {WORD_BITS} * j + i)))")


def words_column(items: Column, k: int) -> Column:
    """Word array of an array of distinct items."""
    bit = lambda i: F.call_function("shiftleft", F.lit(1).cast("long"), (i % WORD_BITS).cast("int"))
    word = lambda j: F.aggregate(F.filter(items, lambda i: F.floor(i / WORD_BITS) == j), F.lit(0).cast("long"), lambda a, i: a.bitwiseOR(bit(i)))
    return F.array(*[word(j) for j in range(max(1, -(-k // WORD_BITS)))])


def wide_stats(ct: DataFrame, k: int) -> DataFrame:
    """Rows, items, distinct rows and share of ones in %."""
    ones = F.aggregate("w", F.lit(0).cast("long"), lambda a, x: a + F.bit_count(x))
    s = ct.agg(F.sum("n").alias("n_rows"), F.count("*").alias("distinct_rows"), F.sum(ones * F.col("n")).alias("ones"))
    return s.select("n_rows", F.lit(k).alias("items"), "distinct_rows", F.round(F.col("ones") * 100.0 / (F.col("n_rows") * k), 4).alias("pct_ones"))


def item_supports(ct: DataFrame, k: int) -> DataFrame:
    """(item, supp) of every item, those that never occur included: one partial and one final aggregation."""
    found = ct.select("n", F.explode(items_in()).alias("item")).groupBy("item").agg(F.sum("n").alias("supp"))
    every = ct.sparkSession.range(k).select(F.col("id").cast("int").alias("item"))
    return every.join(found, "item", "left").select("item", F.coalesce("supp", F.lit(0).cast("long")).alias("supp"))


def itemset_supports(ct: DataFrame, sets: DataFrame) -> DataFrame:
    """Support of each word array `mask` of `sets` over distinct rows: a containment join."""
    sets = sets.select("mask").distinct()
    found = contains_join(ct, sets).groupBy("mask").agg(F.sum("n").alias("supp"))
    return sets.join(found, "mask", "left").select("mask", F.coalesce("supp", F.lit(0).cast("long")).alias("supp"))


def cooccurrence(ct: DataFrame) -> DataFrame:
    """(i, j, c): rows with both items, i <= j; the items of a distinct row are paired inside the row."""
    x = ct.select("n", items_in().alias("x")).select("n", "x", F.explode_outer("x").alias("i"))  # outer: see itemsets.cooccurrence
    return x.select("n", "i", F.explode_outer(F.filter("x", lambda j: j >= F.col("i"))).alias("j")).where("j IS NOT NULL").groupBy("i", "j").agg(F.sum("n").alias("c"))


def independent(ct: DataFrame, k: int) -> DataFrame:
    """Bits of the single-leaf model: (n_rows, bits). The one row with the total is joined by a constant."""
    total = ct.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_rows"))
    cost = codelen.leaf_cost_col(F.col("n_rows"), F.col("supp"))
    return item_supports(ct, k).crossJoin(F.broadcast(total)).groupBy("n_rows").agg(F.round(F.sum(cost), 4).alias("bits"))
