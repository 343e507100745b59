"""Registered operator queries against their SQL, and the pipeline against a brute-force version of it."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as cp
from codetrees.llm import packing, quality, queries
from tests.llm.test_operators import brute_components, brute_contamination, lower


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_equals_sql(spark, sf_dir, duck, same, name):
    same(queries.QUERIES[name](spark, sf_dir), duck(queries.ORACLES[name]))


def test_all_ten_are_registered():
    import __spark_entry__ as e

    names = e.queries()
    assert all(any(n.startswith(f"op{i}_") for n in names) for i in range(1, 11)) and "pipeline" in names


def brute_pipeline(spark, sf_dir):
    docs = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()]
    bench = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    df = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = quality.train_quality_model(df, spark.read.parquet(f"{sf_dir}/labels.parquet").where(~quality.held_out()))
    good = {r["doc_id"] for r in quality.score_quality(df, model).where("predicted = 1").collect()}
    docs = [d for d in docs if d[0] in good]
    last = {}
    for i, t in docs:
        last[lower(t)] = max(i, last.get(lower(t), -1))
    docs = [d for d in docs if last[lower(d[1])] == d[0]]
    parts, _ = brute_components(docs)
    docs = [d for d in docs if any(k[0] == d[0] and k[2] == d[0] for k in parts if k[0] == d[0])]
    dirty = {k[0] for k in brute_contamination(docs, bench) if k[-1]}
    return [d for d in docs if d[0] not in dirty]


def test_pipeline(spark):
    sf_dir = "/root/testdata/sf0.001"
    want = brute_pipeline(spark, sf_dir)
    got = cp.run(spark, sf_dir)
    assert {r["doc_id"] for r in got.select("doc_id").distinct().collect()} == {i for i, _ in want}
    e = packing.encoder(packing.default_tokenizer())
    assert got.agg(F.sum("length")).first()[0] == sum(len(e(t)) + 1 for _, t in want)
    assert got.groupBy("sequence_id").agg(F.sum("length").alias("n")).where("n > 1024").isEmpty()


def test_stages_pass_columns_and_odd_rows_through(spark, tmp_path):
    sf_dir = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(40)
    odd = spark.createDataFrame([(None, None, None, None, None), (None, "x y z", "en", "s", 5), (None, "x y z", "en", "s", 5), (None, "other words here", "en", "s", 5), (3, "", "en", None, 0), (3, "", "en", None, 0)], docs.schema)
    rows = docs.unionByName(odd).withColumn("kept", F.lit("clash")).withColumn("w", F.lit(1))
    rows.write.parquet(str(tmp_path / "in"))
    for name, stage in cp.STAGES[:-1]:
        src = spark.read.parquet(str(tmp_path / "in"))
        out = stage(spark, src, sf_dir)
        assert out.columns == src.columns, name
        kept = out.where("doc_id is null").count()
        if name == "exact dedup":
            assert kept == 2  # two texts; the null text equals the empty one of id 3, which stays
        assert stage(spark, src.limit(0), sf_dir).count() == 0
    assert cp.STAGES[-1][1](spark, rows, sf_dir).where("doc_id is null").count() == 4
