"""The itemset-cover compressor used for comparison. It describes only the ones of each row.

A table of itemsets, always with all singletons, is walked in cover order (larger first, then higher support, then lower
mask); an itemset is taken when it lies inside the ones not yet covered. Usages give code lengths. Candidates are tried in
order of support, then size; one is kept when table and data together get shorter. With prune, entries whose usage fell
are dropped again when that shortens the whole.
"""

from __future__ import annotations

import math
from bisect import bisect_left
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codetrees.plans.counts import LocalCounts, SparkCounts
from codetrees.plans.model import items_of
from codetrees.sources.tables import scratch


FIT_CELLS = 4_000_000  # pairs of a row and an entry that are looked at together


@dataclass
class Cover:
    """Accepted itemsets in cover order, usages of itemsets and singletons, bits of the start and of the result."""

    table: list[int]
    usage: dict[int, int]
    start_bits: float
    bits: float
    tried: int
    truncated: bool

    def ratio(self) -> float:
        return 100.0 * self.bits / self.start_bits if self.start_bits else 100.0

    def n_sets(self) -> int:
        """Itemsets of two or more items in use."""
        return sum(1 for m, u in self.usage.items() if m.bit_count() > 1 and u > 0)


def _usages(rows: np.ndarray, n: np.ndarray, table: list[int], k: int) -> dict[int, int]:
    rest, out = rows.copy(), {}
    for x in table:
        v = np.int64(x)
        hit = (rest & v) == v
        if hit.any():
            out[x] = int(n[hit].sum())
            rest[hit] &= ~v
    for i in range(k):
        u = int(n[(rest >> np.int64(i)) & np.int64(1) == 1].sum())
        if u:
            out[1 << i] = u
    return out


def total_bits(usage: dict[int, int], single: dict[int, float]) -> float:
    """Data bits plus, for every entry in use, its own code and its items spelt with the singleton code."""
    total = sum(usage.values())
    bits = 0.0
    for m, u in usage.items():
        if u > 0:
            length = -np.log2(u / total)
            bits += u * length + length + sum(single[i] for i in items_of(m))
    return float(bits)


class Bits:
    """What total_bits would change by, from the entries that change alone: with U usages in all of c entries, the bits are
    (U + c) log U - sum of (u + 1) log u, and the items' own codes."""

    def __init__(self, usage: dict[int, int], single: dict[int, float]):
        self.usage, self.single = usage, single
        self.total, self.used = sum(usage.values()), sum(1 for u in usage.values() if u > 0)

    def change(self, change: dict[int, int]) -> float:
        total, used, bits = self.total, self.used, 0.0
        for m, d in change.items():
            u = self.usage.get(m, 0)
            total += d
            used += (u + d > 0) - (u > 0)
            if u > 0:
                bits += (u + 1) * math.log2(u)
            if u + d > 0:
                bits -= (u + d + 1) * math.log2(u + d)
            if (u > 0) != (u + d > 0):
                bits += (1 if d > 0 else -1) * float(sum(self.single[i] for i in items_of(m)))
        # (U' + c') log U' - (U + c) log U, without the difference of two large numbers
        grown = math.log2(total) * (total + used - self.total - self.used) if total else 0.0
        return bits + grown + ((self.total + self.used) * math.log1p((total - self.total) / self.total) / math.log(2) if total and self.total else 0.0)

    def add(self, change: dict[int, int]) -> None:
        for m, d in change.items():
            u = self.usage.get(m, 0)
            self.usage[m] = u + d
            self.total += d
            self.used += (u + d > 0) - (u > 0)


def _fitting(rest: np.ndarray, entries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Takes the entries, in their order, from rows of different masks, in place: the numbers of rows and of the entries
    that they take. Of the entries that fit in a row, all rows take their first one together, until none fits."""
    rows, places = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    step = max(1, FIT_CELLS // max(1, len(entries)))
    for at in range(0, len(rest) if len(entries) else 0, step):
        some = rest[at : at + step]
        i, e = np.nonzero((some[:, None] & entries) == entries)
        while len(i):
            first = np.ones(len(i), bool)
            first[1:] = i[1:] != i[:-1]
            rows.append(i[first] + at)
            places.append(e[first])
            some[i[first]] &= ~entries[e[first]]
            still = (some[i] & entries[e]) == entries[e]
            i, e = i[still], e[still]
    return np.concatenate(rows), np.concatenate(places)


class Walk:
    """Compact rows, and what is left of them behind the entries of each size or more, kept as the table grows. A candidate
    stands last among the entries of its size, since candidates are tried in that order: only rows in which it still fits
    there change, and only from there on. Rows of which the same is left are looked at once."""

    def __init__(self, rows: np.ndarray, n: np.ndarray, k: int, table=()):
        self.kind = np.uint32 if k <= 32 else np.int64
        self.rows, self.n, self.k = rows.astype(self.kind), n, k
        self.start(table)

    def start(self, table) -> None:
        """Walks the rows through a table in cover order."""
        self.table: dict[int, np.ndarray] = {}  # entries by size
        self.left: dict[int, np.ndarray] = {}
        for size in sorted({x.bit_count() for x in table}, reverse=True):
            some = self.table[size] = np.array([x for x in table if x.bit_count() == size], self.kind)
            rest = self._above(size).copy()
            for v in some:
                hit = np.flatnonzero((rest & v) == v)
                rest[hit] &= ~v
            self.left[size] = rest

    def _above(self, size: int) -> np.ndarray:
        """What is left of the rows behind the entries of at least this size."""
        return self.left[min((s for s in self.left if s >= size), default=0)] if any(s >= size for s in self.left) else self.rows

    def _below(self, size: int) -> list[int]:
        return sorted((s for s in self.table if s < size), reverse=True)

    def _fits(self, x: int) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of the rows in which x fits, and what is left of them there."""
        rest, v = self._above(x.bit_count()), self.kind(x)
        at = np.flatnonzero((rest & v) == v)
        return at, rest[at]

    def change(self, x: int) -> dict[int, int]:
        """Usages that change when x joins the table: {mask: difference}."""
        at, rest = self._fits(x)
        rest, of = np.unique(rest, return_inverse=True)
        n = np.zeros(len(rest), np.int64)
        np.add.at(n, of, self.n[at])
        entries = np.concatenate([np.zeros(0, self.kind), *(self.table[s] for s in self._below(x.bit_count()))])
        used, ones = np.zeros(len(entries), np.int64), np.zeros(self.k, np.int64)
        for sign, some in ((-1, rest), (1, rest & ~self.kind(x))):
            i, e = _fitting(some, entries)
            np.add.at(used, e, sign * n[i])
            ones += sign * np.array([n[(some >> self.kind(b)) & self.kind(1) == 1].sum() for b in range(self.k)], np.int64)
        at = np.flatnonzero(used)
        out = {x: int(n.sum())} | dict(zip(entries[at].tolist(), used[at].tolist(), strict=True)) | {1 << int(b): int(ones[b]) for b in np.flatnonzero(ones)}
        return {m: u for m, u in out.items() if u}

    def join(self, x: int) -> None:
        """x joins the table."""
        size = x.bit_count()
        at, rest = self._fits(x)
        if size not in self.left:
            self.left[size] = self._above(size).copy()
        self.table[size] = np.append(self.table.get(size, np.zeros(0, self.kind)), self.kind(x))
        rest, of = np.unique(rest & ~self.kind(x), return_inverse=True)
        self.left[size][at] = rest[of]
        for s in self._below(size):
            _fitting(rest, self.table[s])
            self.left[s][at] = rest[of]


class LocalRows:
    """Usages from compact rows on the driver; candidates are looked at one by one."""

    most = 1

    def __init__(self, counts: LocalCounts):
        self.rows, self.n, self.k = counts.words[:, 0].view(np.int64), counts.n, counts.k
        self.walk = Walk(self.rows, self.n, self.k)

    def usages(self, table: list[int]) -> dict[int, int]:
        return _usages(self.rows, self.n, table, self.k)

    def changes(self, table: list[int], tries: list[int]) -> list[dict[int, int]]:
        return [self.walk.change(x) for x in tries]

    def join(self, x: int) -> None:
        self.walk.join(x)

    def start(self, table: list[int]) -> None:
        self.walk.start(table)


class SparkRows:
    """The same by one job per table or batch of candidates; sums per partition reach the driver, rows never do. The
    compact rows are written once to the shared folder, so that jobs do not make them again."""

    most = 256

    def __init__(self, counts: SparkCounts):
        spark = counts.ct.sparkSession
        path = scratch(spark, "cover")
        counts.ct.select(F.col("m"), F.col("n").cast("long").alias("n")).repartition(2 * spark.sparkContext.defaultParallelism).write.parquet(path)
        self.ct, self.k = spark.read.parquet(path), counts.k

    def _sums(self, work) -> dict[tuple[int, int], int]:
        """work: a function of rows and multiplicities to (number, mask, amount) triples, summed over partitions."""

        def partial(batches):
            import pyarrow as pa

            got = [(b.column("m").to_numpy().view(np.int64), b.column("n").to_numpy()) for b in batches]
            if got:
                i, m, u = np.array(work(np.concatenate([x for x, _ in got]), np.concatenate([y for _, y in got])), np.int64).reshape(-1, 3).T
                yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary()) for x in (i, m, u)], names=["i", "m", "u"])

        out: dict[tuple[int, int], int] = {}
        for r in self.ct.mapInArrow(partial, "i binary, m binary, u binary").toLocalIterator():  # one partition's sums at a time
            for i, m, u in zip(*(np.frombuffer(r[c], np.int64).tolist() for c in "imu"), strict=True):
                out[i, m] = out.get((i, m), 0) + u
        return out

    def usages(self, table: list[int]) -> dict[int, int]:
        k = self.k
        return {m: u for (_, m), u in self._sums(lambda rows, n: [(0, m, u) for m, u in _usages(rows, n, table, k).items()]).items()}

    def changes(self, table: list[int], tries: list[int]) -> list[dict[int, int]]:
        k = self.k

        def work(rows, n):
            some = np.zeros(len(rows), bool)
            for x in tries:
                some |= (rows & np.int64(x)) == np.int64(x)
            walk = Walk(rows[some], n[some], k, table)
            return [(i, m, u) for i, x in enumerate(tries) for m, u in walk.change(x).items()]

        out: list[dict[int, int]] = [{} for _ in tries]
        for (i, m), u in self._sums(work).items():
            if u:
                out[i][m] = u
        return out

    def join(self, x: int) -> None:
        """The next job walks its rows through the table anew."""

    start = join


def cover_baseline(counts, family: dict[int, int], prune: bool = False, max_candidates: int | None = None) -> Cover:
    """Search a code table over compact rows, on the driver or by Spark jobs, as the counts are. Candidates are weighed in
    batches against the table of the time; those after one that is kept are weighed again. max_candidates stops early and
    says so in `truncated`."""
    k = counts.k
    if k > 63:
        raise ValueError("the cover baseline takes at most 63 items")
    data = SparkRows(counts) if isinstance(counts, SparkCounts) else LocalRows(counts)
    ones = {i: 0 for i in range(k)} | {m.bit_length() - 1: u for m, u in data.usages([]).items()}
    whole = sum(ones.values())
    single = {i: -np.log2(c / whole) if c else 0.0 for i, c in ones.items()}
    usage = {1 << i: u for i, u in ones.items() if u}
    start = total_bits(usage, single)
    place = lambda m: (-m.bit_count(), -family[m], m)
    wanted = sorted((m for m in family if m.bit_count() > 1), key=lambda m: (-family[m], -m.bit_count(), m))
    last = len(wanted) if max_candidates is None else min(max_candidates, len(wanted))
    table: list[int] = []
    tried, width, weigh = 0, min(8, data.most), Bits(usage, single)
    while tried < last:
        batch = wanted[tried : min(last, tried + width)]
        kept = False
        for x, change in zip(batch, data.changes(table, batch), strict=True):
            tried += 1
            if weigh.change(change) < -1e-9:
                fell = [m for m in table if change.get(m, 0) < 0]
                weigh.add(change)
                table.insert(bisect_left(table, place(x), key=place), x)
                data.join(x)
                kept = True
                if prune and fell:
                    less, usage = _prune(data, table, weigh.usage, fell, single)
                    if len(less) < len(table):
                        data.start(less)
                        table, weigh = less, Bits(usage, single)
                break
        width = max(1, min(8, data.most), width // 2) if kept else min(data.most, 2 * width)
    usage = weigh.usage
    return Cover(table, {m: u for m, u in usage.items() if u > 0}, start, total_bits(usage, single), tried, tried < len(wanted))


def _prune(data, table, usage, fell, single):
    todo, best = sorted(fell, key=lambda m: usage.get(m, 0)), total_bits(usage, single)
    while todo:
        x = todo.pop(0)
        less = [m for m in table if m != x]
        made = data.usages(less)
        bits = total_bits(made, single)
        if bits < best - 1e-9:
            todo += [m for m in less if made.get(m, 0) < usage.get(m, 0) and m not in todo]
            table, usage, best = less, made, bits
    return table, usage


def cover_start(ct: DataFrame, k: int) -> DataFrame:
    """Bits of the table of singletons, by one aggregation: (ones, data_bits, table_bits, start_bits)."""
    sums = ct.agg(*[F.sum(F.expr(f"n * (shiftright(m, {i}) & 1)")).alias(f"c{i}") for i in range(k)])
    one = sums.select(F.explode(F.array(*[F.col(f"c{i}") for i in range(k)])).alias("u")).where("u > 0")
    total = one.agg(F.sum("u").alias("ones"))
    length = -F.log2(F.col("u") / F.col("ones"))
    out = one.crossJoin(F.broadcast(total)).groupBy("ones").agg(F.sum(F.col("u") * length).alias("d"), F.sum(2 * length).alias("t"))
    return out.select("ones", F.round("d", 4).alias("data_bits"), F.round("t", 4).alias("table_bits"), F.round(F.col("d") + F.col("t"), 4).alias("start_bits"))


def cover_usage(ct: DataFrame, table: list[int], k: int) -> DataFrame:
    """Usage of each entry of a given table over all compact rows: a fold over the table inside each row."""
    entries = F.array(*[F.lit(x).cast("long") for x in [*table, *(1 << i for i in range(k))]])
    start = F.struct(F.col("m").alias("rest"), F.array().cast("array<bigint>").alias("used"))

    def take(acc, x):
        hit = acc["rest"].bitwiseAND(x) == x
        return F.struct(F.when(hit, acc["rest"].bitwiseAND(F.bitwise_not(x))).otherwise(acc["rest"]).alias("rest"), F.when(hit, F.concat(acc["used"], F.array(x))).otherwise(acc["used"]).alias("used"))

    used = F.aggregate(entries, start, take, lambda acc: acc["used"])
    return ct.select("n", F.explode(used).alias("mask")).groupBy("mask").agg(F.sum("n").alias("usage"))
