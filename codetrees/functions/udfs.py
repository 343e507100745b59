"""Python functions for Spark: vectorised scalar and aggregate UDFs, a table function, Arrow and grouped maps, SQL names."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from codetrees.functions import codelen


@F.pandas_udf(T.DoubleType())
def nml_bits_udf(m: pd.Series) -> pd.Series:
    """Leaf complexity of m rows."""
    return pd.Series(codelen.nml_bits(m.to_numpy()))


@F.pandas_udf(T.DoubleType())
def leaf_bits_udaf(n: pd.Series, n1: pd.Series) -> float:
    """Data bits of a tree from its leaves' counts. A group is one tree's leaves."""
    return float(codelen.data_bits(n.to_numpy(), n1.to_numpy()).sum())


@F.udtf(returnType=T.StructType([T.StructField("mask", T.LongType())]))
class leaf_sets_udtf:
    """Itemsets of a leaf: pos with any part of neg, with and without the target."""

    def eval(self, pos: int, neg: int, target: int):
        sub = neg
        while True:
            yield (pos | sub,)
            yield (pos | sub | 1 << target,)
            if not sub:
                break
            sub = (sub - 1) & neg


def gram_table(ct: DataFrame, k: int) -> DataFrame:
    """(i, j, c): pair counts of compact rows by one matrix product per partition and a sum of small rows."""
    from codetrees.plans.counts import _columns, gram

    def run(batches):
        import numpy as np
        import pyarrow as pa

        total = np.zeros((k, k), np.int64)
        for b in batches:
            words, n = _columns(b)
            total += gram(words, n, k)[:k, :k].astype(np.int64)
        i, j = np.indices((k, k), np.int32)
        yield pa.RecordBatch.from_arrays([pa.array(i.ravel()), pa.array(j.ravel()), pa.array(total.ravel())], names=["i", "j", "c"])

    return ct.select("m", "n").mapInArrow(run, "i int, j int, c long").groupBy("i", "j").agg(F.sum("c").alias("c"))


def fit_by_class(rows: DataFrame, k: int) -> DataFrame:
    """One model per label, fitted inside its group. rows: (label, m), aggregated to distinct rows before they are grouped."""
    ct = rows.groupBy("label", "m").agg(F.count("*").alias("n"))

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        import numpy as np

        from codetrees.plans.counts import LocalCounts
        from codetrees.plans.greedy import grow_model

        c = LocalCounts(pdf["m"].to_numpy().astype(np.int64).view(np.uint64).reshape(-1, 1), pdf["n"].to_numpy(), k)
        m = grow_model(c, [f"i{x}" for x in range(k)])
        return pd.DataFrame({"label": [pdf["label"].iloc[0]], "n_rows": [c.total], "bits": [m.cost()], "model": [m.to_json()]})

    return ct.groupBy("label").applyInPandas(fit, "label string, n_rows long, bits double, model string")


def register(spark: SparkSession) -> SparkSession:
    """SQL names of the functions."""
    spark.udf.register("codetrees_nml_bits", nml_bits_udf)
    spark.udf.register("codetrees_leaf_bits", leaf_bits_udaf)
    spark.udtf.register("codetrees_leaf_sets", leaf_sets_udtf)
    return spark
