"""The certificates must find what is wrong."""

import dataclasses

import pandas as pd

from codetrees.plans import certificates as cert
from codetrees.plans.core_queries import literal_model
from codetrees.sources.workloads import WORKLOADS
from codetrees.streaming import stream_queries


def test_wrong_leaf_counts_are_found(spark, sf_dir):
    m, ct = literal_model(spark, sf_dir), WORKLOADS["w5"].compact(spark, sf_dir)
    assert cert.wrong_leaves(ct, m) == 0
    key = next(k for k, (n, _) in m.counts.items() if n)
    changed = dataclasses.replace(m, counts=m.counts | {key: (m.counts[key][0] - 1, m.counts[key][1])})
    assert cert.wrong_leaves(ct, changed) == 1


def test_early_tests_are_found(spark, sf_dir):
    m = literal_model(spark, sf_dir)
    assert cert.order_violations(m) == 0

    class Backward(type(m)):
        def order(self):
            return super().order()[::-1]

    assert cert.order_violations(Backward(**{f.name: getattr(m, f.name) for f in dataclasses.fields(m)})) == 4


def test_previous_event_of_a_key_in_many_arrow_batches(spark, tmp_path):
    rows = pd.DataFrame({"user_id": 1, "event_id": range(3000), "event_type": [f"e{i}" for i in range(3000)]}).sample(frac=1, random_state=1)
    spark.createDataFrame(rows).write.parquet(f"{tmp_path}/events.parquet")
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, "100")
    try:
        got = {r["event_id"]: r["prev"] for r in stream_queries.Q["o58_stateful"](spark, str(tmp_path)).collect()}
    finally:
        spark.conf.set(key, before)
    assert got == {0: None} | {i: f"e{i - 1}" for i in range(1, 3000)}


def test_item_lists_are_made_of_compact_rows_only(spark, sf_dir):
    from codetrees.operators import itemsets, wide
    from codetrees.sources.tables import wide_items

    for df in (itemsets.cooccurrence(WORKLOADS["w5"].compact(spark, sf_dir), 18), wide.cooccurrence(wide_items(spark, sf_dir, 120)[0])):
        assert "size(" not in df._jdf.queryExecution().optimizedPlan().toString()
    empty = spark.createDataFrame([(0, 3)], "m long, n long")
    assert itemsets.cooccurrence(empty, 5).count() == 0
    assert wide.cooccurrence(spark.createDataFrame([([0, 0], 3)], "w array<long>, n long")).count() == 0
