"""Every query of the library against its SQL, and certificates where SQL has no say."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from codetrees.operators import apply as ap
from codetrees.operators import itemsets as it
from codetrees.operators import relational as rel
from codetrees.plans import core_queries as core
from codetrees.plans import registry
from codetrees.plans.counts import LocalCounts, SparkCounts, counts_of
from codetrees.plans.greedy import grow_model
from codetrees.sources.workloads import WORKLOADS

QUERIES, SQL = registry.queries(), registry.oracle_sql()


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_equals_sql(spark, sf_dir, duck, same, name):
    same(QUERIES[name](spark, sf_dir), duck(SQL[name]))


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(SQL)))
def test_query_runs(spark, sf_dir, name):
    assert QUERIES[name](spark, sf_dir).count() > 0


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())


@pytest.mark.parametrize("name", ["w2", "w5", "w7", "w9"])
def test_spark_counts_grow_the_same_model(spark, sf_dir, name):
    w = WORKLOADS[name]
    ct = w.compact(spark, sf_dir).cache()
    local, far = counts_of(ct, w.k), counts_of(ct, w.k, local_cells=0)
    assert isinstance(local, LocalCounts) and isinstance(far, SparkCounts)
    a, b = grow_model(local, w.names), grow_model(far, w.names)
    assert a.trees == b.trees and a.counts == b.counts
    assert far.scans < 2 + len(b.trace)
    assert local.supports([1, 3, 7]) == far.supports([1, 3, 7])
    ct.unpersist()


def test_toy_results(spark, sf_dir):
    assert core.grown(spark, sf_dir, "w1")[0].trace == []
    m, _ = core.grown(spark, sf_dir, "w2")
    assert m.cost() == pytest.approx(10_884.13, abs=0.02) and len(m.itemsets()) == 19 and len(m.itemsets(True)) == 20
    assert [(t, j) for t, _, _, j, _, _ in m.trace] == [(5, 4), (6, 5), (8, 7), (2, 1), (3, 2), (7, 6), (0, 1), (9, 8), (4, 3)]


@pytest.mark.parametrize("name", ["w4", "w5", "w6", "w7", "w8", "w9"])
def test_growth_beats_the_independent_model(spark, sf_dir, name):
    r = core.grow_row(spark, sf_dir, name)
    assert r["bits"] < r["base_bits"]


def test_growth_bits_are_row_bits(spark, sf_dir):
    m, _ = core.grown(spark, sf_dir, "w9")
    p = WORKLOADS["w9"].packed(spark, sf_dir)
    got = ap.code_length(p, m, "ml").agg(F.sum("bits")).first()[0]
    assert got == pytest.approx(m.data_bits(), rel=1e-9)
    assert ap.code_length(p, m, "kt", most_leaves=0).agg(F.sum("bits")).first()[0] == pytest.approx(ap.code_length(p, m, "kt").agg(F.sum("bits")).first()[0])


def test_language_is_told_far_above_majority(spark, sf_dir):
    r = core.classify_row(spark, sf_dir, "lang").first()
    assert r["accuracy"] > r["majority"] + 0.3


def test_null_predicates_count_as_false(spark):
    df = spark.createDataFrame([(1, None), (2, 5)], "k int, v int")
    assert [tuple(x) for x in rel.project_items(df, {"a": "v > 3"}).collect()] == [(False,), (True,)]


def test_closure_reports_missing_parts(spark):
    f = spark.createDataFrame([(1,), (3,)], "mask long")
    assert [r["part"] for r in it.closure_violations(f).collect()] == [2]
    assert not it.is_downward_closed(f) and it.is_downward_closed(it.close_downward(f))


def test_unknown_symbols_cost_infinity_only_unsmoothed():
    assert ap.symbol_bits(5, 0, "ml") == float("inf") and np.isfinite(ap.symbol_bits(5, 0, "kt")) and ap.symbol_bits(0, 0, "ml") == 1


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_compaction_has_one_exchange_and_reads_its_columns(spark, sf_dir):
    text = plan(WORKLOADS["w5"].compact(spark, sf_dir))
    assert text.count("Exchange hashpartitioning") == 1
    assert "l_comment" not in text and "o_custkey" not in text.split("ReadSchema")[1].split("\n")[0]


def test_scoring_has_no_exchange(spark, sf_dir):
    assert "Exchange" not in plan(ap.code_length(WORKLOADS["w5"].packed(spark, sf_dir), core.literal_model(spark, sf_dir)))


def test_filters_reach_the_scan(spark, sf_dir):
    assert "PushedFilters: [IsNotNull(o_orderkey), LessThan(o_orderkey,2000)]" in plan(WORKLOADS["w1"].packed(spark, sf_dir))


def test_join_small_shuffles_beyond_its_limit(spark, sf_dir):
    a, b = spark.range(100), spark.range(50)
    assert "BroadcastExchange" in plan(rel.join_small(a, b, "id"))
    assert rel.join_small(a, b, "id", limit=10).count() == 50


def test_large_families_refuse_to_broadcast(spark):
    from codetrees.plans.select import spark_batch

    class Big(dict):
        def __len__(self):
            return 10_000_001

    with pytest.raises(ValueError):
        spark_batch(spark, Big(), 3, "greedy", "refined")
