"""Shared pieces of the training-data operators: shared-folder tables, row keys, worker caches."""

from __future__ import annotations

import gc
import sys
import tempfile
import uuid
import zlib

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
RID = "__rid"


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir; where it is unset, a temporary one if driver and executors
    are one process, else the warehouse."""
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not base and spark.sparkContext.master.split("[")[0] != "local":
        base = spark.conf.get("spark.sql.warehouse.dir")
    if not base:
        base = worker_cache().setdefault("own_shared_dir", None) or tempfile.mkdtemp(prefix="codetrees-")
        worker_cache()["own_shared_dir"] = base
    return base.rstrip("/")


def written(df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    small_batches(spark)
    path = f"{shared_dir(spark)}/codetrees/{uuid.uuid4().hex}-{name}"
    df.write.parquet(path)
    trimmed(spark)
    out = spark.read.schema(df.schema).parquet(path)
    out._codetrees_path = path
    return out


def dropped(*tables: DataFrame) -> None:
    """Delete tables made by written() that nothing reads any more."""
    for t in tables:
        path = getattr(t, "_codetrees_path", None)
        if path:
            jvm, jsc = t.sparkSession._jvm, t.sparkSession._jsc
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(jsc.hadoopConfiguration()).delete(p, True)


def small_batches(spark: SparkSession, most: int = 4 << 20) -> None:
    """Bound the bytes of the Arrow batches that Python workers get, as texts can be long: a setting of the session that
    may change at run time, lowered only where it is larger."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = str(spark.conf.get(name))
    if not now.rstrip("bB").isdigit() or int(now.rstrip("bB")) > most:
        spark.conf.set(name, str(most))


def tidy(run):
    """A function for mapInArrow that gives memory back to the system when its task is done: worker processes stay alive
    for later tasks, and what they keep would add up."""

    def tidied(batches):
        try:
            yield from run(batches)
        finally:
            import ctypes

            import pyarrow as pa

            gc.collect()
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL("libc.so.6").malloc_trim(0)
            except (OSError, AttributeError):
                pass  # another C library

    return tidied


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner delete the shuffle files of plans that are no longer referenced, as the driver seldom
    collects its garbage by itself; and give what the driver's JVM has freed outside its heap back to the system."""
    gc.collect()
    spark._jvm.System.gc()
    trimmed(spark)


def trimmed(spark: SparkSession) -> bool:
    """Have the driver's JVM return its freed native memory to the system; False where it cannot."""
    from py4j.protocol import Py4JError

    jvm = spark._jvm
    try:
        beans = jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer()
        # By reflection, as Py4J finds no method for the two nulls that are meant as no arguments.
        invoke = next(m for m in jvm.java.lang.Class.forName("javax.management.MBeanServer").getMethods() if m.getName() == "invoke")
        args = spark.sparkContext._gateway.new_array(jvm.java.lang.Object, 4)
        args[0], args[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        invoke.invoke(beans, args)
    except Py4JError:  # another JVM or C library
        return False
    return True


def ascii_lower(c: Column) -> Column:
    """Lower-case A-Z and nothing else."""
    return F.translate(c, UPPER, UPPER.lower())


def fresh(name: str, *tables: DataFrame) -> str:
    """name, with underscores added until no table has such a column."""
    have = {c.lower() for t in tables for c in t.columns}
    while name.lower() in have:
        name += "_"
    return name


def keyed(df: DataFrame, id_col: str, cols: list[str], row_col: str | None = None) -> DataFrame:
    """df's cols plus a unique long RID: the column row_col, if the caller names one that is unique and never null; else
    the id itself when it is an integer, never null and never repeated (one aggregation over the id column decides); else
    rows are numbered and written once, so that the numbers stay. A column of df that is itself called RID is left out."""
    small_batches(df.sparkSession)
    cols = [c for c in dict.fromkeys([id_col, *cols]) if c != RID]
    if row_col:
        return df.select(F.col(row_col).cast("long").alias(RID), *(c for c in cols if c != RID))
    if df.schema[id_col].dataType.typeName() in ("byte", "short", "integer", "long"):
        ids = df.groupBy(id_col).count().where((F.col("count") > 1) | F.col(id_col).isNull())
        if ids.isEmpty():
            out = df.select(F.col(id_col).cast("long").alias(RID), *cols)
            out._codetrees_rid_is_id = True
            return out
    return written(df.select(F.monotonically_increasing_id().alias(RID), *cols), "keyed")


def worker_cache() -> dict:
    """A dict that outlives a task in its Python process (functions pickled by value lose their module's globals)."""
    return sys.__dict__.setdefault("_codetrees_cache", {})


def crc32_mod(c: Column, m: int) -> Column:
    """crc32 of the value as text, modulo m."""
    return F.crc32(F.encode(c.cast("string"), "UTF-8")) % m


def py_crc32_mod(value, m: int) -> int:
    return zlib.crc32(str(value).encode()) % m


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x
