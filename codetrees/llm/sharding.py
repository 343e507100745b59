"""Sharding by extendible hashing: a directory over hash-prefix bits in which only oversized buckets split.

Documents hash to 32 bits of md5(id). Byte sums are taken once per cell (a prefix of `depth` bits, pre-aggregated before
the shuffle); each cell then looks for its shortest prefix whose bytes fit the limit. Cells that do not fit even at
their own depth go on, alone, with more bits. A bucket that no bits can split (one id's rows, or one huge document) gets
overflow shards: rows in order, a new shard whenever the limit would be passed; a row larger than the limit has a shard
of its own.

Edge rules: null text has 0 bytes; null ids hash as the text "null"; repeated rows share a bucket; an empty table gives
an empty result; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from codetrees.llm.common import RID, dropped, fresh, keyed, tidy, written

BITS = 32
LIMIT = 64 << 10  # bytes of text in a shard: small here, so that the given tables have many shards


def hash_bits(c: Column) -> Column:
    """First 32 bits of md5 of the value as text, as a long."""
    return F.conv(F.substring(F.md5(F.coalesce(c.cast("string"), F.lit("null")).cast("binary")), 1, 8), 16, 10).cast("long")


def _prefix(h: Column, depth) -> Column:
    return F.shiftrightunsigned(h, F.lit(BITS) - depth) if isinstance(depth, Column) else F.shiftrightunsigned(h, BITS - depth)


def directory(rows: DataFrame, limit: int, step: int = 10) -> DataFrame:
    """rows: h, n_bytes -> the leaves: depth, prefix, shard_bytes, fits. Cells are looked at `step` bits at a time."""
    leaves, todo, low = [], rows.select("h", "n_bytes"), 0
    while low <= BITS:
        high = min(BITS, low + step)
        cells = todo.groupBy(_prefix(F.col("h"), high).alias("cell")).agg(F.sum("n_bytes").alias("b"))
        levels = cells.select("cell", "b", F.explode(F.sequence(F.lit(low), F.lit(high))).alias("depth"))
        levels = levels.withColumn("prefix", F.expr(f"shiftrightunsigned(cell, {high} - depth)"))
        sums = levels.groupBy("depth", "prefix").agg(F.sum("b").alias("shard_bytes"))
        full = levels.join(sums, ["depth", "prefix"])
        fit = full.where(F.col("shard_bytes") <= limit).groupBy("cell").agg(F.min("depth").alias("depth"))
        level = cells.join(fit, "cell", "left").select("cell", F.col("depth"))
        level = written(level, "directory")
        done = level.where("depth is not null").select("depth", F.expr(f"shiftrightunsigned(cell, {high} - depth)").alias("prefix")).distinct()
        leaves.append(written(done.join(sums, ["depth", "prefix"]).withColumn("fits", F.lit(True)), "leaves"))
        over = level.where("depth is null").select("cell")
        if high == BITS:
            leaves.append(over.join(cells, "cell").select(F.lit(BITS).alias("depth"), F.col("cell").alias("prefix"), F.col("b").alias("shard_bytes"), F.lit(False).alias("fits")))
            break
        if over.isEmpty():
            break
        todo = rows.select("h", "n_bytes").join(over, _prefix(F.col("h"), high) == F.col("cell"), "left_semi")
        low = high + 1
    out = leaves[0]
    for x in leaves[1:]:
        out = out.unionByName(x)
    return written(out, "directory")


def extendible_shards(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", limit: int = LIMIT, row_col: str | None = None) -> DataFrame:
    """One row per input row: RID, id, shard (prefix bits as text, "" for the root, "-k" added in overflow), depth,
    n_bytes, shard_bytes."""
    docs = keyed(df, id_col, [text_col], row_col)
    rows = docs.select(RID, id_col, hash_bits(F.col(id_col)).alias("h"), F.coalesce(F.octet_length(text_col), F.lit(0)).cast("long").alias("n_bytes"))
    rows = written(rows, "sizes")
    leaves = directory(rows, limit)
    depths = [r[0] for r in leaves.select("depth").distinct().collect()]  # at most 33
    # A leaf is found by the prefix of its own depth: each row carries its prefixes at the depths in use.
    probe = rows.withColumn("depth", F.explode(F.array(*[F.lit(d) for d in sorted(depths)] or [F.lit(0)])))
    probe = probe.withColumn("prefix", F.expr(f"shiftrightunsigned(h, {BITS} - depth)"))
    hit = probe.join(leaves, ["depth", "prefix"])
    bits = F.when(F.col("depth") == 0, F.lit("")).otherwise(F.expr("lpad(conv(cast(prefix as string), 10, 2), depth, '0')"))
    hit = hit.withColumn("shard", bits)
    fits = hit.where("fits")
    late = hit.where("not fits")
    chained = written(late.select("shard", RID, "n_bytes").repartition("shard").sortWithinPartitions("shard", RID).mapInArrow(tidy(_chain(limit)), f"shard string, {RID} long, k int, n_bytes long"), "overflow")
    sums = chained.groupBy("shard", "k").agg(F.sum("n_bytes").alias("part_bytes"))
    over = late.drop("shard", "n_bytes", "shard_bytes").join(chained.join(sums, ["shard", "k"]), RID)
    over = over.withColumn("shard", F.concat("shard", F.lit("-"), F.col("k"))).withColumn("shard_bytes", F.col("part_bytes"))
    cols = [RID, id_col, "shard", "depth", "n_bytes", "shard_bytes"]
    return fits.select(*cols).unionByName(over.select(*cols))


def _chain(limit: int):
    """Sorted by bucket and row: the number of the overflow shard of each row. Only a running sum is held."""

    def run(batches):
        import pyarrow as pa

        bucket, k, total = None, 0, 0
        for b in batches:
            out = []
            for shard, n in zip(b.column("shard").to_pylist(), b.column("n_bytes").to_pylist(), strict=True):
                if shard != bucket:
                    bucket, k, total = shard, 0, 0
                if total and total + n > limit:
                    k, total = k + 1, 0
                total += n
                out.append(k)
            yield pa.RecordBatch.from_arrays([b.column("shard"), b.column(RID), pa.array(out, pa.int32()), b.column("n_bytes")], names=["shard", RID, "k", "n_bytes"])

    return run


def write_shards(df: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", limit: int = LIMIT) -> DataFrame:
    """Write df, all its rows and columns, as one folder per shard under path and return the assignment. Rows are told
    apart by an own number, so ids may be null or repeated. The folder's column is "shard", with underscores added where
    df has such a column."""
    rows = written(df.select(F.monotonically_increasing_id().alias(row := fresh("row", df)), "*"), "rows")
    assigned = written(extendible_shards(rows, id_col, text_col, limit, row), "assigned")
    name = fresh("shard", rows)
    out = rows.join(assigned.select(F.col(RID).alias(row), F.col("shard").alias(name)), row).drop(row)
    out.repartition(name).write.partitionBy(name).parquet(path)
    dropped(rows)
    return assigned


def op4_extendible_shards(spark, sf_dir: str) -> DataFrame:
    """Shards of at most LIMIT bytes of text over all documents."""
    return extendible_shards(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop(RID)


def op4_sql(limit: int = LIMIT, depth: int = 32) -> str:
    return f"""
WITH RECURSIVE r AS (SELECT doc_id, coalesce(strlen(text), 0)::BIGINT AS n_bytes,
                  ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT AS h FROM documents),
     s AS (SELECT d.d AS depth, r.h >> (32 - d.d) AS prefix, sum(n_bytes)::BIGINT AS b
           FROM r, (SELECT unnest(range(0, {depth + 1})) AS d) d GROUP BY ALL),
     f AS (SELECT r.doc_id, r.n_bytes, r.h, min(s.depth) AS depth
           FROM r JOIN s ON s.prefix = r.h >> (32 - s.depth) WHERE s.b <= {limit} GROUP BY ALL),
     o AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY h ORDER BY doc_id) AS i FROM r WHERE doc_id NOT IN (SELECT doc_id FROM f)),
     c(h, i, doc_id, n_bytes, k, total) AS (
       SELECT h, i, doc_id, n_bytes, 0, n_bytes FROM o WHERE i = 1
       UNION ALL
       SELECT o.h, o.i, o.doc_id, o.n_bytes, CASE WHEN c.total > 0 AND c.total + o.n_bytes > {limit} THEN c.k + 1 ELSE c.k END,
              CASE WHEN c.total > 0 AND c.total + o.n_bytes > {limit} THEN o.n_bytes ELSE c.total + o.n_bytes END
       FROM c JOIN o ON o.h = c.h AND o.i = c.i + 1)
SELECT f.doc_id, CASE WHEN f.depth = 0 THEN '' ELSE right(lpad(bin(f.h), 32, '0')[1:f.depth], f.depth) END AS shard,
       f.depth::INTEGER AS depth, f.n_bytes, s.b AS shard_bytes
FROM f JOIN s ON s.depth = f.depth AND s.prefix = f.h >> (32 - f.depth)
UNION ALL
SELECT doc_id, lpad(bin(h), 32, '0') || '-' || k, 32::INTEGER, n_bytes, (sum(n_bytes) OVER (PARTITION BY h, k))::BIGINT FROM c
"""
