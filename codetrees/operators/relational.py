"""Surrounding DataFrame operators: item building, joins, aggregations, windows, set operations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

BROADCAST_ROWS = 2_000_000

# ---- scans and items


def load(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None) -> DataFrame:
    """A table's scan with only the columns asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def project_items(df: DataFrame, catalog: dict[str, str]) -> DataFrame:
    """Boolean items of predicates given as SQL text; null counts as false."""
    return df.select(*[F.coalesce(F.expr(e), F.lit(False)).alias(n) for n, e in catalog.items()])


def one_hot(df: DataFrame, col: str, values: list, keep: list[str]) -> DataFrame:
    return df.select(*keep, *[F.coalesce(F.col(col) == v, F.lit(False)).alias(f"{col}_{i}") for i, v in enumerate(values)])


def threshold_items(df: DataFrame, col: str, cuts: list, keep: list[str]) -> DataFrame:
    return df.select(*keep, *[F.coalesce(F.col(col) > c, F.lit(False)).alias(f"{col}_gt_{i}") for i, c in enumerate(cuts)])


def equi_width(df: DataFrame, col: str, low: float, high: float, bins: int) -> DataFrame:
    """Bin numbers 1..bins of equal width, 0 and bins + 1 outside."""
    return df.withColumn("bin", F.expr(f"width_bucket({col}, {low}D, {high}D, {bins})"))


def quantile_cuts(df: DataFrame, col: str, shares: list[float], approximate: bool = False) -> DataFrame:
    """Equi-depth cuts: exact percentiles, or sketches of bounded size."""
    f = F.percentile_approx if approximate else F.percentile
    return df.agg(*[f(F.col(col), F.lit(q)).alias(f"q{i}") for i, q in enumerate(shares)])


def pack(df: DataFrame, items: list[str], keep: list[str]) -> DataFrame:
    """Boolean columns to one mask (up to 63)."""
    bits = [F.when(F.col(c), F.lit(1 << i)).otherwise(F.lit(0)).cast("long") for i, c in enumerate(items)]
    return df.select(*keep, sum(bits[1:], bits[0]).alias("m"))


def unpack(df: DataFrame, names: list[str], keep: list[str]) -> DataFrame:
    return df.select(*keep, *[(F.expr(f"shiftright(m, {i}) & 1") == 1).alias(n) for i, n in enumerate(names)])


def pack_words(df: DataFrame, items: list[str], keep: list[str], word_bits: int = 63) -> DataFrame:
    """Any number of boolean columns to words of word_bits bits."""
    words = []
    for at in range(0, len(items), word_bits):
        bits = [F.when(F.col(c), F.lit(1 << i)).otherwise(F.lit(0)).cast("long") for i, c in enumerate(items[at : at + word_bits])]
        words.append(sum(bits[1:], bits[0]))
    return df.select(*keep, F.array(*words).alias("w"))


# ---- joins


def join_small(a: DataFrame, b: DataFrame, on, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Equi-join that broadcasts b when it has at most `limit` rows (counted), and shuffles otherwise."""
    return a.join(F.broadcast(b), on) if b.limit(limit + 1).count() <= limit else a.join(b, on)


def join_large(a: DataFrame, b: DataFrame, on, hint: str = "merge") -> DataFrame:
    """Equi-join of two large sides: "merge" or "shuffle_hash"; skewed keys are split at run time."""
    return a.join(b.hint(hint), on)


def contains_join(rows: DataFrame, sets: DataFrame, limit: int = 10_000) -> DataFrame:
    """Rows (m, or w for word arrays) with every set (mask, of the same kind) inside them. At most `limit` sets (counted) are broadcast; more are joined by their
    lowest item with the rows' items, the empty set by an item that all rows have."""
    wide = "m" not in rows.columns
    inside = F.expr("forall(zip_with(w, mask, (a, b) -> a & b = b), x -> x)" if wide else "m & mask = mask")
    if sets.limit(limit + 1).count() <= limit:
        return rows.join(F.broadcast(sets), inside)
    item = next(n for n in ("item", "item_", "item__") if n not in rows.columns + sets.columns)
    if wide:
        bits = "flatten(transform({0}, (x, j) -> transform(filter(sequence(0, 62), i -> (shiftright(x, i) & 1) = 1), i -> 63 * j + i)))"
        items, lowest = F.concat(F.array(F.lit(-1)), F.expr(bits.format("w"))), F.expr(f"coalesce(get({bits.format('mask')}, 0), -1)")
    else:
        items = F.concat(F.array(F.lit(-1)), F.expr("filter(sequence(0, 62), i -> (shiftright(m, i) & 1) = 1)"))
        lowest = F.when(F.col("mask") == 0, F.lit(-1)).otherwise(F.expr("bit_count((mask & -mask) - 1)"))
    return rows.withColumn(item, F.explode(items)).join(sets.withColumn(item, lowest), item).where(inside).drop(item)


def bin_join(df: DataFrame, bins: DataFrame, value: str) -> DataFrame:
    """Range join with a few bins (lo <= value < hi), which are counted before they are broadcast."""
    if bins.limit(BROADCAST_ROWS + 1).count() > BROADCAST_ROWS:
        raise ValueError(f"more than {BROADCAST_ROWS} bins")
    return df.join(F.broadcast(bins), (F.col(value) >= F.col("lo")) & (F.col(value) < F.col("hi")))


def asof_prev(a: DataFrame, b: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """Each row of a with the last `value` of b at or before its time, by key: one shuffle, no range join."""
    left = a.withColumn("__side", F.lit(1)).withColumn("__v", F.lit(None).cast(b.schema[value].dataType))
    right = b.select(key, ts, F.col(value).alias("__v"), F.lit(0).alias("__side"))
    both = left.unionByName(right, allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(ts, "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn("prev", F.last("__v", ignorenulls=True).over(w)).where("__side = 1").drop("__side", "__v")


def within(a: DataFrame, b: DataFrame, key: str, ts: str, seconds: int) -> DataFrame:
    """Pairs of equal key whose times differ by at most `seconds`: rows meet in time buckets of that width."""
    bucket = lambda c: F.floor(F.unix_timestamp(c.cast("timestamp")) / seconds)
    left = a.withColumn("__b", bucket(F.col(ts)))
    right = b.withColumnsRenamed({c: f"r_{c}" for c in b.columns})
    right = right.withColumn("__b", F.explode(F.array(*[bucket(F.col(f"r_{ts}")) + d for d in (-1, 0, 1)])))
    near = F.abs(F.unix_timestamp(F.col(ts).cast("timestamp")) - F.unix_timestamp(F.col(f"r_{ts}").cast("timestamp"))) <= seconds
    return left.join(right, (F.col(key) == F.col(f"r_{key}")) & (left["__b"] == right["__b"]) & near).drop("__b")


def item_pairs(items: DataFrame) -> DataFrame:
    """(i, j), i < j, of the distinct values of items' column i."""
    i = items.select(F.col("i").cast("int").alias("i")).distinct()
    return i.crossJoin(F.broadcast(i.select(F.col("i").alias("j")))).where("i < j")


# ---- aggregations


def to_baskets(df: DataFrame, key: str, item: str) -> DataFrame:
    return df.groupBy(key).agg(F.array_sort(F.collect_set(item)).alias("items"))


def presence(df: DataFrame, key: list[str], preds: dict[str, str]) -> DataFrame:
    return df.groupBy(*key).agg(*[F.bool_or(F.coalesce(F.expr(e), F.lit(False))).alias(n) for n, e in preds.items()], *[F.count_if(F.expr(e)).alias(f"n_{n}") for n, e in preds.items()])


def cells(df: DataFrame, cols: list[str], mode: str) -> DataFrame:
    """Counts of all cells of a cube or rollup with the grouping id."""
    grouped = df.cube(*cols) if mode == "cube" else df.rollup(*cols)
    return grouped.agg(F.grouping_id().cast("long").alias("gid"), F.count("*").alias("n"))


def corr_items(df: DataFrame, a: str, b: str) -> DataFrame:
    x, y = F.col(a).cast("double"), F.col(b).cast("double")
    return df.agg(F.round(F.corr(x, y), 8).alias("corr"), F.round(F.covar_pop(x, y), 8).alias("covar"), F.round(F.stddev_pop(x), 8).alias("sd_a"), F.round(F.stddev_pop(y), 8).alias("sd_b"))


def mutual_information(ct: DataFrame, i: int, j: int) -> DataFrame:
    """Bits shared by two items, from compact rows."""
    x = ct.select(F.expr(f"shiftright(m, {i}) & 1").alias("a"), F.expr(f"shiftright(m, {j}) & 1").alias("b"), "n")
    ab = x.groupBy("a", "b").agg(F.sum("n").alias("n"))
    w = lambda *c: Window.partitionBy(*c) if c else Window.partitionBy(F.lit(0))
    t, na, nb = F.sum("n").over(w()), F.sum("n").over(w("a")), F.sum("n").over(w("b"))
    return ab.select((F.col("n") / t * F.log2(F.col("n") * t / (na * nb))).alias("p")).agg(F.round(F.sum("p"), 8).alias("bits"))


def frequent_values(df: DataFrame, col: str, minsup: int) -> DataFrame:
    return df.groupBy(col).count().where(F.col("count") >= minsup)


# ---- windows


def best_per_group(df: DataFrame, part: list[str], order: list[Column]) -> DataFrame:
    return df.withColumn("__r", F.row_number().over(Window.partitionBy(*part).orderBy(*order))).where("__r = 1").drop("__r")


def shifted(df: DataFrame, part: str, order: list[str], col: str) -> DataFrame:
    w = Window.partitionBy(part).orderBy(*order)
    full = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return df.select(*df.columns, F.lag(col).over(w).alias("prev"), F.lead(col).over(w).alias("next"), F.first(col).over(full).alias("first"), F.nth_value(col, 2).over(full).alias("second"))


def running(df: DataFrame, part: str, order: list[str], col: str) -> DataFrame:
    w = Window.partitionBy(part).orderBy(*order)
    return df.withColumn("so_far", F.sum(col).over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow))).withColumn("last3", F.sum(col).over(w.rowsBetween(-2, 0)))


def top_k(df: DataFrame, order: list[Column], k: int) -> DataFrame:
    """The first k rows of an order: kept per task, then merged; never a full sort."""
    return df.orderBy(*order).limit(k)


# ---- text and nested values


def tokens(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    return df.select(*keep, F.explode(F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit("[a-z]+"), 0))).alias("token"))


def vocabulary(df: DataFrame, text: str, k: int) -> DataFrame:
    """The k tokens of most documents; ties by the alphabet."""
    return tokens(df, text, []).groupBy("token").count().orderBy(F.desc("count"), "token").limit(k)


def dedupe(df: DataFrame, on: list[str], order: str) -> DataFrame:
    """One row per value of `on`, the one with the least `order`."""
    return df.groupBy(*on).agg(F.min(order).alias(order), F.count("*").alias("copies"))
