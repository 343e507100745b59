"""Connected components of a link table, distributed: alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codetrees.llm.common import dropped, written


def _both(e: DataFrame) -> DataFrame:
    return e.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(e.select(F.col("b").alias("u"), F.col("a").alias("v")))


def _star(e: DataFrame, large: bool) -> DataFrame:
    """Large: neighbours above u point to the least of u's neighbourhood; small: u and those below it do.

    The least neighbour is aggregated before it is joined back, so no neighbourhood is ever gathered."""
    n = _both(e) if large else e.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
    least = n.groupBy("u").agg(F.least(F.min("v"), F.min("u")).alias("m"))
    out = n.join(least, "u")
    out = out.where("v > u").select(F.col("v").alias("a"), F.col("m").alias("b")) if large else out.select(F.col("v").alias("a"), F.col("m").alias("b")).unionByName(least.select(F.col("u").alias("a"), F.col("m").alias("b")))
    return out.where("a <> b").distinct()


def _of(table: DataFrame, view: DataFrame) -> DataFrame:
    """view, which dropped() deletes together with the table it reads."""
    view._codetrees_path = getattr(table, "_codetrees_path", None)
    return view


def label_components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """links: a, b (longs) -> node, label for every node in a link; label is the least node of its component."""
    e = written(links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    if e.isEmpty():
        return _of(e, e.select(F.col("a").alias("node"), F.col("b").alias("label")))
    state = None
    for _ in range(most_rounds):
        new = written(_star(_star(e, True), False), "stars")
        now = new.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        dropped(e)
        e = new
        if now == state:
            break
        state = now
    else:
        raise RuntimeError("components did not settle")
    # Settled: every node but the least of its component has one edge, to that least node.
    roots = e.select(F.col("b").alias("node"), F.col("b").alias("label")).distinct()
    return _of(e, e.select(F.col("a").alias("node"), F.col("b").alias("label")).unionByName(roots))
