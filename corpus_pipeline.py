"""Corpus pipeline: quality, exact copies, near copies, benchmark passages, then packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and read again as the next
stage's docs. All stages but the last return the columns of docs. Rows are told apart by an own number where doc_id is
null or repeated, so nulls, repeated rows and extra columns pass through every stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codetrees.llm import decontaminate, exact_dedup, ngram_join, packing, quality
from codetrees.llm.common import RID, dropped, fresh, keyed, written

ORACLE_SQL = None  # neither a trained classifier nor packing can be expressed in SQL; see tests/llm/test_pipeline.py


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier does not reject; learnt from the labelled rows of docs that are not held out."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = quality.train_quality_model(docs, labels.where(~quality.held_out()))
    return quality.keep_quality(docs, model)


def _numbered(docs: DataFrame) -> tuple[DataFrame, str]:
    """docs with a row number, under a name that it lacks."""
    row = fresh("row", docs)
    hidden = docs.toDF(*(f"c{i}" for i in range(len(docs.columns))))
    out = keyed(hidden, f"c{docs.columns.index('doc_id')}", hidden.columns)
    return out.toDF(*(row if c == RID else docs.columns[int(c[1:])] for c in out.columns)), row


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents with equal text (A-Z lower-cased) the one with the largest doc_id."""
    rows, row = _numbered(docs)
    kept = exact_dedup.exact_dedup(rows, keep="largest", row_col=row).where("kept").select(F.col(RID).alias(row))
    return rows.join(kept, row, "left_semi").select(*docs.columns)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents connected by links of Jaccard at least 0.75 the one with the least doc_id."""
    rows, row = _numbered(docs)
    kept = ngram_join.jaccard_components(rows, row_col=row).where("representative").select(F.col(RID).alias(row))
    return rows.join(kept, row, "left_semi").select(*docs.columns)


def benchmark_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that are not contaminated by benchmark passages."""
    return decontaminate.decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents left, in sequences of at most 1024 tokens."""
    return packing.pack(docs, packing.default_tokenizer())


STAGES = [
    ("quality classifier", quality_stage),
    ("exact dedup", exact_stage),
    ("n-gram Jaccard join", near_stage),
    ("benchmark decontamination", benchmark_stage),
    ("best-fit packing", packing_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        before, docs = docs, written(stage(spark, docs, sf_dir), name.replace(" ", "-"))
        dropped(before)
    return STAGES[-1][1](spark, docs, sf_dir)
