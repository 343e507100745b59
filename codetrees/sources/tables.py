"""Readers, writers, generators and plan inspection."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

FORMATS = ("csv", "json", "orc", "parquet")
_OWN: dict[str, str] = {}


def scratch(spark: SparkSession, name: str) -> str:
    """A new path in the folder that the cluster shares: spark.checkpoint.dir; where it is unset, a temporary folder if
    driver and executors are one process, else the warehouse."""
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not base and spark.sparkContext.master.split("[")[0] != "local":
        base = spark.conf.get("spark.sql.warehouse.dir")
    if not base:
        base = _OWN["dir"] = _OWN.get("dir") or tempfile.mkdtemp(prefix="codetrees-")
    return f"{base.rstrip('/')}/codetrees-io/{uuid.uuid4().hex}-{name}"


def read_baskets(spark: SparkSession, path: str, sep: str = " ") -> DataFrame:
    """Transaction files: one line a transaction, item numbers separated by `sep`; an empty line is an empty basket."""
    parts = F.filter(F.split("value", re.escape(sep)), lambda x: x != "")
    return spark.read.text(path).select(F.transform(parts, lambda x: x.cast("int")).alias("items"))


def write_baskets(baskets: DataFrame, path: str, sep: str = " ") -> None:
    baskets.select(F.concat_ws(sep, F.transform("items", lambda x: x.cast("string"))).alias("value")).write.text(path)


def baskets_to_masks(baskets: DataFrame) -> DataFrame:
    return baskets.select(F.expr("aggregate(items, 0L, (a, i) -> a | shiftleft(1L, i)) AS m"))


def basket_roundtrip(packed: DataFrame, k: int) -> DataFrame:
    """Baskets written with their key as the last item, read again: (key, items as text)."""
    spark = packed.sparkSession
    items = F.expr(f"filter(sequence(0, {k - 1}), i -> (shiftright(m, i) & 1) = 1)")
    path = scratch(spark, "baskets")
    write_baskets(packed.select(F.concat(items, F.array((F.col("key") + k).cast("int"))).alias("items")), path)
    back = read_baskets(spark, path)
    text = F.concat(F.lit("["), F.concat_ws(", ", F.transform(F.slice("items", F.lit(1), F.size("items") - 1), lambda x: x.cast("string"))), F.lit("]"))
    return back.select((F.element_at("items", -1) - k).cast("long").alias("key"), text.alias("items"))


def read_any(spark: SparkSession, path: str, fmt: str, schema) -> DataFrame:
    """csv, json, orc or parquet with an explicit schema."""
    return spark.read.format(fmt).schema(schema).load(path)


def write_any(df: DataFrame, path: str, fmt: str) -> None:
    df.write.format(fmt).save(path)


def format_roundtrip(df: DataFrame) -> DataFrame:
    spark, out = df.sparkSession, None
    for fmt in FORMATS:
        path = scratch(spark, fmt)
        write_any(df, path, fmt)
        got = read_any(spark, path, fmt, df.schema).agg(F.lit(fmt).alias("format"), F.count("*").alias("n_rows"), F.round(F.sum("p_retailprice"), 2).alias("price"), F.min("p_name").alias("first_name"))
        out = got if out is None else out.unionByName(got)
    return out


def toy(keys: DataFrame, k: int, kind: str = "independent", seed: int = 0, flip: str = "1a") -> DataFrame:
    """A generated row (key, a1..ak) for every row of keys (key): independent fair items, or a chain in which each item differs from the one before with
    a probability of `flip` (two hex digits) in 256. By md5, so the same everywhere."""
    byte = lambda i: F.substring(F.md5(F.concat_ws("-", F.lit(str(seed)), F.col("key").cast("string"), F.lit(str(i))).cast("binary")), 1, 2)
    rows = keys.select(F.col("key").cast("long").alias("key"))
    if kind == "independent":
        return rows.select("key", *[(byte(i) < "80").alias(f"a{i}") for i in range(1, k + 1)])
    flips = [(byte(i) < ("80" if i == 1 else flip)).cast("int") for i in range(1, k + 1)]
    return rows.select("key", *[(sum(flips[1:i], flips[0]) % 2 == 1).alias(f"a{i}") for i in range(1, k + 1)])


def model_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A grown model saved and loaded: same cost, same trees."""
    from codetrees.plans.core_queries import grown, one_row
    from codetrees.plans.model import load_model, save_model

    m, _ = grown(spark, sf_dir, "w5")
    path = scratch(spark, "model")
    save_model(m, spark, path, "w5")
    got = load_model(spark, path, "w5")
    return one_row(spark, bits=got.cost(), same=got.trees == m.trees and got.counts == m.counts)


def global_rank(df: DataFrame, order: list[Column], keep: list[str]) -> DataFrame:
    """Place of each row in a total order without one task seeing all rows: a range-partitioned sort, ranks inside the
    partitions, and the sizes of the partitions before."""
    part = df.orderBy(*order).withColumn("__p", F.spark_partition_id())
    path = scratch(df.sparkSession, "sorted")
    part.write.parquet(path)
    got = df.sparkSession.read.parquet(path)
    from pyspark.sql import Window

    got = got.withColumn("__r", F.row_number().over(Window.partitionBy("__p").orderBy(*order)))
    sizes = got.groupBy("__p").agg(F.count("*").alias("__n"))
    before = sizes.select("__p", F.coalesce(F.sum("__n").over(Window.orderBy("__p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__b"))
    return got.join(F.broadcast(before), "__p").select(*keep, (F.col("__b") + F.col("__r")).alias("place"))


def plan_of(df: DataFrame, mode: str = "formatted") -> str:
    """The physical plan as text."""
    return df._jdf.queryExecution().explainString(df._sc._jvm.org.apache.spark.sql.execution.ExplainMode.fromString(mode)) if hasattr(df, "_sc") else df._jdf.queryExecution().toString()


def plan_nodes(df: DataFrame) -> dict[str, int]:
    """How often each physical operator occurs in the plan."""
    plan = df._jdf.queryExecution().executedPlan()
    if plan.getClass().getSimpleName() == "AdaptiveSparkPlanExec":
        plan = plan.executedPlan()  # the present one of the plans that the text would show
    text = plan.toString()
    out: dict[str, int] = {}
    for line in text.splitlines():
        m = re.match(r"^[\s:+|*()0-9-]*([A-Z][A-Za-z]+)", line)
        if m:
            out[m[1]] = out.get(m[1], 0) + 1
    return out


def plan_table(df: DataFrame) -> DataFrame:
    """Physical operators of the plan that has run: all rows are made, by Spark's tasks, and counted; the stages' own nodes
    are left out."""
    made = df._jdf.queryExecution()
    made.toRdd().count()
    rows = sorted((a, b) for a, b in plan_nodes(df).items() if not a.endswith("QueryStage"))
    return df.sparkSession.createDataFrame([(a, b) for a, b in rows], "operator string, n int")


def _word(names: list[str]) -> Column:
    """Mask of the names that array column t holds."""
    part = F.array(*[F.lit(x) for x in names])
    place = F.transform(F.array_intersect(F.col("t"), part), lambda x: F.call_function("shiftleft", F.lit(1).cast("long"), (F.array_position(part, x) - 1).cast("int")))
    return F.aggregate(place, F.lit(0).cast("long"), lambda a, x: a.bitwiseOR(x))


def wide_rows(spark: SparkSession, sf_dir: str, k: int = 120, word_bits: int = 63) -> tuple[DataFrame, list[str]]:
    """More items than a mask holds: (key, lang, w) with the presence of the k commonest tokens of documents, in
    alphabetical order, as word arrays. A null text has no token."""
    from codetrees.operators.relational import vocabulary

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "lang", "text")
    names = sorted(r["token"] for r in vocabulary(docs, "text", k).collect())  # k names
    found = F.array_intersect(F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit("[a-z]+"), 0), F.array(*[F.lit(x) for x in names]).cast("array<string>"))
    words = [_word(names[at : at + word_bits]) for at in range(0, len(names), word_bits)]
    return docs.select(F.col("doc_id").alias("key"), "lang", found.alias("t")).select("key", "lang", F.array(*words).alias("w")), names


def wide_items(spark: SparkSession, sf_dir: str, k: int = 120, word_bits: int = 63) -> tuple[DataFrame, list[str]]:
    """Distinct wide rows with their multiplicities: (w, n)."""
    rows, names = wide_rows(spark, sf_dir, k, word_bits)
    return rows.groupBy("w").agg(F.count("*").alias("n")), names


def wide_growth(spark: SparkSession, sf_dir: str, max_splits: int | None = None) -> DataFrame:
    """Growth on 120 items until no split saves bits."""
    from codetrees.plans.core_queries import one_row
    from codetrees.plans.counts import counts_of
    from codetrees.plans.greedy import grow_model
    from codetrees.plans.model import independent_cost

    ct, names = wide_items(spark, sf_dir)
    c = counts_of(ct, len(names))
    m = grow_model(c, names, max_splits=max_splits)
    base = independent_cost([c.path(0, 0, i)[1] for i in range(len(names))], c.total)
    return one_row(spark, n_rows=c.total, items=len(names), base_bits=base, bits=m.cost(), splits=len(m.trace))
