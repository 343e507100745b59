"""Rows with more items than one mask holds, against brute force over Python sets."""

import random

import pytest
from pyspark.sql import functions as F

from codetrees.operators import apply as ap
from codetrees.operators import wide
from codetrees.operators.relational import contains_join
from codetrees.plans import core_queries as core
from codetrees.plans.counts import counts_of
from codetrees.plans.greedy import grow_model
from codetrees.plans.wide_queries import chain_model
from codetrees.sources.tables import wide_rows
from codetrees.sources.workloads import WORKLOADS

K = 130
NAMES = [f"i{i}" for i in range(K)]


def words(items):
    return [sum(1 << i % 63 for i in items if i // 63 == j) for j in range(3)]


@pytest.fixture(scope="module")
def sets():
    r = random.Random(3)
    base = [frozenset(i for i in range(K) if r.random() < 0.2) for _ in range(40)] + [frozenset(), frozenset(range(K))]
    return [r.choice(base) for _ in range(300)]


@pytest.fixture(scope="module")
def packed(spark, sets):
    return spark.createDataFrame([(i, words(s)) for i, s in enumerate(sets)], "key long, w array<long>").cache()


@pytest.fixture(scope="module")
def distinct(packed):
    return packed.groupBy("w").agg(F.count("*").alias("n")).cache()


def test_items_and_words_are_inverse(packed, sets):
    got = packed.select("key", wide.items_in().alias("x"), (wide.words_column(wide.items_in(), K) == F.col("w")).alias("same")).collect()
    assert all(r["same"] and r["x"] == sorted(sets[r["key"]]) for r in got)


def test_statistics_and_supports(distinct, sets):
    s = wide.wide_stats(distinct, K).first()
    assert (s["n_rows"], s["distinct_rows"]) == (300, len(set(sets)))
    assert s["pct_ones"] == pytest.approx(100 * sum(map(len, sets)) / (300 * K), abs=1e-3)
    assert {r["item"]: r["supp"] for r in wide.item_supports(distinct, K).collect()} == {i: sum(i in s for s in sets) for i in range(K)}
    pairs = {(r["i"], r["j"]): r["c"] for r in wide.cooccurrence(distinct).collect()}
    assert pairs[5, 100] == sum({5, 100} <= s for s in sets) and pairs[62, 63] == sum({62, 63} <= s for s in sets)


@pytest.mark.parametrize("limit", [0, 100])
def test_containment_join_broadcast_or_by_item(spark, distinct, sets, limit):
    wanted = [frozenset(), {0}, {62, 63}, {5, 70, 129}, {126}]
    masks = spark.createDataFrame([(words(x),) for x in wanted], "mask array<long>")
    got = contains_join(distinct, masks, limit).groupBy("mask").agg(F.sum("n").alias("c")).collect()
    assert {tuple(r["mask"]): r["c"] for r in got} == {tuple(words(x)): sum(x <= s for s in sets) for x in wanted}
    found = wide.itemset_supports(distinct, masks.union(masks)).collect()
    assert {tuple(r["mask"]): r["supp"] for r in found} == {tuple(words(x)): sum(x <= s for s in sets) for x in wanted}


def test_empty_tables(spark, distinct):
    none = distinct.limit(0)
    assert wide.wide_stats(none, K).first()["distinct_rows"] == 0
    assert wide.item_supports(none, K).agg(F.sum("supp")).first()[0] == 0
    assert wide.cooccurrence(none).count() == 0


def test_scoring_routing_and_residuals(packed, distinct, sets):
    model = chain_model(counts_of(distinct, K), NAMES)
    assert counts_of(distinct, K, local_cells=0).supports([1 << 129, (1 << 5) | (1 << 70)]) == counts_of(distinct, K).supports([1 << 129, (1 << 5) | (1 << 70)])
    lines = {(r["target"], r["leaf"]): (r["n"], r["n1"]) for r in ap.leaf_counts(distinct, model).collect()}
    assert lines == {(r["target"], r["leaf"]): (r["n"], r["n1"]) for r in ap.leaf_counts(distinct, model, 10_000).collect()}
    assert lines[64, 0] == (sum(63 in s for s in sets), sum({63, 64} <= s for s in sets))
    a = {r["key"]: r["bits"] for r in ap.code_length(packed, model).collect()}
    b = {r["key"]: r["bits"] for r in ap.code_length(packed, model, most_leaves=10_000).collect()}
    assert a == pytest.approx(b)
    assert sum(r["bits"] for r in ap.code_length(packed, model, "ml").collect()) == pytest.approx(model.data_bits())
    back = ap.from_residuals(ap.to_residuals(packed, model), model).withColumnRenamed("w", "w2")
    assert packed.join(back, "key").where("w = w2").count() == 300


def test_narrow_leaf_counts_do_not_depend_on_the_way(spark, sf_dir):
    w = WORKLOADS["w9"]
    ct = w.compact(spark, sf_dir)
    model = grow_model(counts_of(ct, w.k), w.names)
    a, b = (sorted(map(tuple, ap.leaf_counts(ct, model, most).collect())) for most in (0, 10_000))
    assert a == b


def test_null_texts_have_no_items(spark, tmp_path):
    docs = spark.createDataFrame([(1, "en", None), (2, None, "a b"), (3, "en", ""), (4, "en", "b c")], "doc_id long, lang string, text string")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    rows, names = wide_rows(spark, str(tmp_path), 120)
    assert names == ["a", "b", "c"]
    assert {r["key"]: r["w"] for r in rows.collect()} == {1: [0], 2: [3], 3: [0], 4: [6]}


@pytest.mark.parametrize("name", ["w3", "w7", "w9"])
def test_exhaustive_selection_needs_no_more_bits_than_the_independent_model(spark, sf_dir, name):
    r = core.select_row(spark, sf_dir, name, "exhaustive")
    assert r["inside"] and r["ratio_pct"] <= 100 + 1e-9
