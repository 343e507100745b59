"""Exact deduplication with a log-structured merge index of text digests.

Map side: each task fills a memtable (digest -> smallest identifier, count); a full memtable is flushed as a sorted run.
Runs are dealt out by digest prefix, so one shard of the index sees all runs of its digests; a hot text arrives as one
entry per flush, never as its rows. In a shard, runs stack up in levels, each with a Bloom filter; `fanout` runs of a
level are merged into one of the next, keeping the smallest identifier and the summed count. Documents whose digest has
other rows then have their bytes compared with the stayer's; should a comparison fail (two texts, one digest), the
digest's rows are grouped again by the texts themselves.

Edge rules: null text counts as empty; ties on the identifier go to the smaller internal row number; repeated rows are
copies of each other; null ids order last; ids of any type that can be ordered serve; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from codetrees.llm.common import RID, ascii_lower, dropped, fresh, keyed, small_batches, tidy, written

KNOWN = 1_000_000  # digests that are broadcast
ENTRY = np.dtype([("d", "S32"), ("order", "<i8"), ("rid", "<i8"), ("n", "<i8")])


class BloomFilter:
    """A byte a place over 64-bit digest heads; `bits_per_key` places a key set the false-positive rate."""

    def __init__(self, heads: np.ndarray, bits_per_key: int = 10, hashes: int = 5):
        self.size, self.hashes = max(64, len(heads) * bits_per_key), hashes
        self.bits = np.zeros(self.size, bool)
        for i in range(hashes):
            self.bits[self._at(heads, i)] = True

    def _at(self, heads, i):
        return (heads >> np.uint64(7 * i)) % np.uint64(self.size)

    def may_hold(self, heads: np.ndarray) -> np.ndarray:
        ok = np.ones(len(heads), bool)
        for i in range(self.hashes):
            ok &= self.bits[self._at(heads, i)]
        return ok


def heads(entries: np.ndarray) -> np.ndarray:
    return np.frombuffer(np.ascontiguousarray(entries["d"]).tobytes(), "S32").view("<u8")[::4].astype(np.uint64) if len(entries) else np.zeros(0, np.uint64)


def merged(runs: list[np.ndarray]) -> np.ndarray:
    """Merge sorted runs: per digest the smallest (order, rid) and the summed count."""
    a = np.concatenate(runs)
    a = a[np.lexsort((a["rid"], a["order"], a["d"]))]
    if not len(a):
        return a
    first = np.concatenate([[True], a["d"][1:] != a["d"][:-1]])
    out = a[first].copy()
    out["n"] = np.add.reduceat(a["n"], np.flatnonzero(first))
    return out


class RunStack:
    """Levels of sorted runs with filters; add() compacts, result() merges only runs that may share digests."""

    def __init__(self, fanout: int = 8):
        self.fanout, self.levels = fanout, []

    def add(self, run: np.ndarray) -> None:
        level = 0
        while True:
            if len(self.levels) <= level:
                self.levels.append([])
            self.levels[level].append((run, BloomFilter(heads(run))))
            if len(self.levels[level]) < self.fanout:
                return
            run = merged([r for r, _ in self.levels[level]])
            self.levels[level] = []
            level += 1

    def result(self) -> np.ndarray:
        runs = [x for level in self.levels for x in level]
        alone, shared = [], []
        for i, (run, _) in enumerate(runs):
            hit = np.zeros(len(run), bool)
            for j, (_, f) in enumerate(runs):
                if i != j:
                    hit |= f.may_hold(heads(run))
            alone.append(run[~hit])
            shared.append(run[hit])
        return np.concatenate([*alone, merged(shared)]) if runs else np.zeros(0, ENTRY)


def _flush_runs(memtable_rows: int, shards: int):
    def run(batches):
        import pyarrow as pa

        held, rows = [], 0

        def flush():
            run = merged(held)
            shard = (np.frombuffer(np.ascontiguousarray(run["d"]).tobytes(), np.uint8).reshape(-1, 32)[:, :4].copy().view(">u4")[:, 0].astype(np.int64) * shards) >> 32
            at = np.concatenate([[0], np.flatnonzero(np.diff(shard)) + 1, [len(run)]]) if len(run) else [0]
            parts = [(int(shard[a]), run[a:b].tobytes()) for a, b in zip(at[:-1], at[1:], strict=True)]
            return pa.RecordBatch.from_arrays([pa.array([p[0] for p in parts], pa.int32()), pa.array([p[1] for p in parts], pa.binary())], names=["shard", "run"])

        for b in batches:
            if not b.num_rows:
                continue
            e = np.zeros(b.num_rows, ENTRY)
            e["d"] = np.frombuffer(b"".join(b["digest"].to_pylist()), "S32")
            e["order"], e["rid"], e["n"] = b["order"].to_numpy(), b[RID].to_numpy(), 1
            held.append(merged([e]))
            rows += len(held[-1])
            if rows >= memtable_rows:
                yield flush()
                held, rows = [], 0
        if held:
            yield flush()

    return run


def _compact(batches):
    import pyarrow as pa

    stacks: dict[int, RunStack] = {}
    for b in batches:
        for shard, run in zip(b["shard"].to_pylist(), b["run"].to_pylist(), strict=True):
            stacks.setdefault(shard, RunStack()).add(np.frombuffer(run, ENTRY))
    for s in stacks.values():
        r = s.result()
        raw = np.ascontiguousarray(r["d"]).tobytes()
        for at in range(0, len(r), 100_000):
            x = r[at : at + 100_000]
            yield pa.RecordBatch.from_arrays(
                [pa.array([raw[32 * i : 32 * i + 32] for i in range(at, at + len(x))], pa.binary()), pa.array(np.ascontiguousarray(x["rid"])), pa.array(np.ascontiguousarray(x["n"]))],
                names=["digest", "keep_rid", "group_size"],
            )


def digest_index(digests: DataFrame, memtable_rows: int = 500_000) -> DataFrame:
    """(digest binary(32), order long, RID long) -> one row per digest: digest, keep_rid, group_size."""
    spark = digests.sparkSession
    shards = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    runs = digests.select("digest", "order", RID).mapInArrow(tidy(_flush_runs(memtable_rows, shards)), "shard int, run binary")
    return runs.repartition(shards, "shard").mapInArrow(tidy(_compact), "digest binary, keep_rid long, group_size long")


def _ordered(docs: DataFrame, id_col: str) -> tuple[DataFrame, Column]:
    """docs with the ids' order as a long: integers are their own; other ids are numbered after one range partitioning."""
    if docs.schema[id_col].dataType.typeName() in ("byte", "short", "integer", "long"):
        return docs, F.col(id_col).cast("long")
    place = fresh("__place", docs)
    ids = docs.select(id_col).where(F.col(id_col).isNotNull()).distinct()
    ids = written(ids.repartitionByRange(id_col).sortWithinPartitions(id_col).withColumn(place, F.monotonically_increasing_id()), "places")
    return docs.join(ids, id_col, "left"), F.col(place)


def exact_dedup(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest", digest_bytes: int = 32, row_col: str | None = None) -> DataFrame:
    """One row per input row: RID, id, keep_id, group_size, kept, text_sha256. Texts are equal when identical after
    lower-casing A-Z. keep: "smallest" or "largest" id stays. digest_bytes: digest length used by the index (short ones,
    for tests, make collisions that the byte comparison must find)."""
    docs = keyed(df, id_col, [text_col], row_col)
    low = ascii_lower(F.coalesce(F.col(text_col), F.lit("")))
    sha = F.sha2(F.encode(low, "UTF-8"), 256)
    sign = 1 if keep == "smallest" else -1
    docs, number = _ordered(docs, id_col)
    order = F.coalesce(sign * number, F.lit((1 << 63) - 1))
    pad = "00" * (32 - digest_bytes)
    digests = written(docs.select(RID, F.col(id_col).alias("id"), order.alias("order"), sha.alias("text_sha256")), "digests")
    digests = digests.withColumn("digest", F.unhex(F.concat(F.substring("text_sha256", 1, 2 * digest_bytes), F.lit(pad))))
    index = written(digest_index(digests), "index")
    again = index.where("group_size > 1")
    # A few digests can hold most rows: those above 1/2000 of all rows, at most 2000 of them, are looked up by broadcast.
    total = index.agg(F.sum("group_size")).first()[0] or 0
    hot = again.where(F.col("group_size") * 2000 > total).where("group_size > 100").limit(2000)
    cold_rows = digests.join(F.broadcast(hot.select("digest")), "digest", "left_anti").join(again.alias("a"), "digest", "left")
    found = cold_rows.unionByName(digests.join(F.broadcast(hot), "digest"))
    found = found.select(RID, "id", "digest", "text_sha256", F.coalesce("keep_rid", F.col(RID)).alias("keep_rid"), F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"))
    found = written(found, "found")

    # Byte comparison, pre-aggregated before its shuffle: all texts of a digest are equal when the least is the greatest.
    # Digests of several rows are broadcast while they are at most KNOWN (32 MB), so that other texts stay where they are.
    texts = docs.select(RID, F.unhex(F.concat(F.substring(sha, 1, 2 * digest_bytes), F.lit(pad))).alias("digest"), low.alias("t"))
    several = again.select("digest")
    several = F.broadcast(several) if several.count() <= KNOWN else several
    hits = texts.join(several, "digest", "left_semi")
    wrong = hits.groupBy("digest").agg(F.min("t").alias("least"), F.max("t").alias("most")).where(F.col("least") != F.col("most")).select("digest")
    wrong = written(wrong, "collided")
    if not wrong.isEmpty():  # one digest, several texts: group these rows by the text itself
        bad = found.join(wrong, "digest").select(RID, "id", "digest", "text_sha256").join(texts.select(RID, "t"), RID).join(digests.select(RID, "order"), RID)
        w = Window.partitionBy("digest", "t")
        o = F.struct(F.col("order"), F.col(RID))
        bad = bad.select(RID, "id", "digest", "text_sha256", F.min(o).over(w)[RID].alias("keep_rid"), F.count("*").over(w).alias("group_size"))
        found = written(found.join(wrong, "digest", "left_anti").unionByName(bad), "regrouped")
    found = found.withColumn("kept", F.col("keep_rid") == F.col(RID))
    if getattr(docs, "_codetrees_rid_is_id", False):
        out = found.withColumn("keep_id", F.col("keep_rid").cast(df.schema[id_col].dataType))
    else:
        names = found.where("kept").select(F.col("keep_rid"), F.col("id").alias("keep_id"))
        out = found.join(names, "keep_rid", "left")
    dropped(index, digests)
    return out.select(RID, F.col("id").alias(id_col), "keep_id", "group_size", "kept", "text_sha256")


def op3_exact_dedup(spark, sf_dir: str) -> DataFrame:
    """Of equal texts of documents the row with the largest doc_id stays."""
    return exact_dedup(spark.read.parquet(f"{sf_dir}/documents.parquet"), keep="largest").drop(RID)


OP3_SQL = """
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, d AS text_sha256
FROM (SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS d FROM documents)
WINDOW w AS (PARTITION BY d)
"""
