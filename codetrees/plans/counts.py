"""Counts over compact data (distinct rows with multiplicities), the only thing that the searches read.

`path statistics` of a set of literals (pos, neg): the number of rows that satisfy them, and for all pairs of items how
many of these rows have both. They serve every target at once and never change, so they are kept by path.

Two sources give the same numbers. SparkCounts runs one job per wave of paths: each partition multiplies its bit matrix
with itself per path, and the partial matrices are summed by path. LocalCounts does it on the driver and is used when the
compact data are at most LOCAL_CELLS bits, which is checked before anything is collected.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codetrees.sources.tables import scratch

LOCAL_CELLS = 64_000_000  # bits, each a byte on the driver
KEPT_BYTES = 64 << 20
WAVE_BYTES = 256 << 20
AHEAD = 256  # paths that growth asks for together, if their matrices take at most AHEAD_BYTES
AHEAD_BYTES = 32 << 20
CHUNK = 20_000
LANE = 255  # zeros and ones that a byte can sum


def bit_matrix(words: np.ndarray, k: int, word_bits: int = 63) -> np.ndarray:
    """(rows, words) unsigned masks to a (rows, k) matrix of 0 and 1."""
    out = np.empty((len(words), k), np.uint8)
    for i in range(k):
        out[:, i] = (words[:, i // word_bits] >> np.uint64(i % word_bits)) & np.uint64(1)
    return out


def masks_to_words(masks: list[int], k: int, word_bits: int = 63) -> np.ndarray:
    full = (1 << word_bits) - 1
    width = max(1, -(-k // word_bits))
    return np.array([[m >> (word_bits * w) & full for w in range(width)] for m in masks], np.uint64).reshape(len(masks), width)


def words_of(column) -> np.ndarray:
    """An Arrow column of masks, or of lists of masks, as (rows, words)."""
    import pyarrow as pa

    if not pa.types.is_list(column.type):
        return column.to_numpy(zero_copy_only=False).view(np.uint64).reshape(-1, 1)
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 1)


def _columns(batch) -> tuple[np.ndarray, np.ndarray]:
    """Masks as (rows, words) and multiplicities of an Arrow batch of (m, n) or (w, n)."""
    return words_of(batch.column(0)), batch.column("n").to_numpy()


def path_rows(words: np.ndarray, pos: np.ndarray, neg: np.ndarray) -> np.ndarray:
    return ((words & pos) == pos).all(1) & ((words & neg) == 0).all(1)


def gram(words: np.ndarray, n: np.ndarray, k: int) -> np.ndarray:
    """k + 1 by k + 1: pair counts of the items, and in the last row and column those of 'any row'."""
    out = np.zeros((k + 1, k + 1))
    for at in range(0, len(n), CHUNK):
        x = np.ones((len(n[at : at + CHUNK]), k + 1))
        x[:, :k] = bit_matrix(words[at : at + CHUNK], k)
        out += x.T @ (x * n[at : at + CHUNK, None])  # exact below 2**53
    return out


class Leaf(NamedTuple):
    """An open leaf of growth: what path() tells of it and, on the driver, the numbers of its rows."""

    n: int
    n1: int
    nj: np.ndarray
    n1j: np.ndarray
    rows: np.ndarray | None = None

    def child(self, item: int, side: bool) -> tuple[int, int]:
        """(n, n1) of the part with the item, or of that without it."""
        n, n1 = int(self.nj[item]), int(self.n1j[item])
        return (n, n1) if side else (self.n - n, self.n1 - n1)


class LocalCounts:
    """Counts from compact rows held on the driver, a byte a bit, by rows and by columns. Rows of paths, and pair counts of
    paths that several targets ask for, are kept while they take at most KEPT_BYTES each. Growth keeps the rows of open
    leaves itself, at most four bytes a bit of the data."""

    def __init__(self, words: np.ndarray, n: np.ndarray, k: int):
        found, rows = np.unique(n, return_counts=True)
        self.usual = int(found[rows.argmax()]) if len(n) else 1  # rows of this multiplicity come last: their bits are summed as they are
        order = np.argsort(n == self.usual, kind="stable")
        self.words, self.n, self.k, self.total = words[order], n[order].astype(np.int64), k, int(n.sum())
        self.others = int((n != self.usual).sum())
        self._lanes = np.zeros((len(n), -(-k // 8)), np.uint64)
        self.bits = self._lanes.view(np.uint8)[:, :k]
        for at in range(0, len(n), CHUNK):
            self.bits[at : at + CHUNK] = bit_matrix(self.words[at : at + CHUNK], k)
        self.columns = np.ascontiguousarray(self.bits.T).view(bool)
        self.scans = 0
        self._rows: dict = {}
        self._grams: dict = {}
        self._asked: dict = {}
        self._size = 0

    def _rows_of(self, pos: int, neg: int) -> np.ndarray:
        """Numbers of the rows at a path, out of those of a known path with one test less."""
        if (pos, neg) in self._rows:
            return self._rows[pos, neg]
        p, q = masks_to_words([pos], self.k)[0], masks_to_words([neg], self.k)[0]
        known = [self._rows.get((pos & ~(1 << i), neg & ~(1 << i))) for i in range(self.k) if (pos | neg) >> i & 1]
        known = [x for x in known if x is not None]
        if known:
            among = min(known, key=len)
            rows = among[path_rows(self.words[among], p, q)]
        else:
            rows = np.flatnonzero(path_rows(self.words, p, q)).astype(np.int32)
        self._rows[pos, neg] = rows
        self._size += rows.nbytes
        while self._size > KEPT_BYTES:
            self._size -= self._rows.pop(next(iter(self._rows))).nbytes
        return rows

    def _sums(self, rows: np.ndarray, target: int | None) -> np.ndarray:
        """Weighted sums of the items, of all rows and of those with the target; without a target: with each item."""
        out = np.zeros((2 if target is not None else self.k + 1, self.k))
        for at in range(0, len(rows), CHUNK):
            some = rows[at : at + CHUNK]
            x, n = self.bits[some].astype(float), self.n[some].astype(float)
            with_item = x.T * n if target is None else (x[:, target] * n)[None]
            out += np.concatenate([n[None], with_item]) @ x  # exact below 2**53
        return out.astype(np.int64)

    def path(self, pos: int, neg: int, target: int) -> tuple[int, int, np.ndarray, np.ndarray]:
        """(n, n1, per item count, per item count with the target) of the rows at a path."""
        key, cost = (pos, neg), 8 * (self.k + 1) * self.k
        if key not in self._grams:
            rows = self._rows_of(pos, neg)
            n = int(self.n[rows].sum())
            asked = self._asked[key] = self._asked.get(key, 0) + 1
            if asked < 2 or (len(self._grams) + 1) * cost > KEPT_BYTES:
                got = self._sums(rows, target)
                return n, int(got[0, target]), got[0], got[1]
            self._grams[key] = n, self._sums(rows, None)
        n, got = self._grams[key]
        return n, int(got[0, target]), got[0], got[1 + target]

    def _ones(self, rows: np.ndarray) -> np.ndarray:
        """Weighted sums of the items over ascending rows. Of rows of the usual multiplicity, eight items take one addition."""
        out, cut = np.zeros(self.k, np.int64), int(np.searchsorted(rows, self.others))
        for at in range(0, cut, CHUNK):
            some = rows[at : min(cut, at + CHUNK)]
            out += (self.n[some].astype(float) @ self.bits[some].astype(float)).astype(np.int64)  # exact below 2**53
        for at in range(cut, len(rows), CHUNK):
            x = self._lanes[rows[at : at + CHUNK]]
            wide = -(-len(x) // LANE)
            whole = len(x) // wide * wide
            sums = x[:whole].reshape(len(x) // wide, -1).sum(0).reshape(wide, -1)
            sums[: len(x) - whole] += x[whole:]
            out += self.usual * sums.view(np.uint8).sum(0, dtype=np.int64)[: self.k]
        return out

    def root(self, target: int) -> Leaf:
        return Leaf(*self.path(0, 0, target), self._rows_of(0, 0))

    def split(self, leaf: Leaf, target: int, item: int, pos: int, neg: int, want) -> list[Leaf | None]:
        """The wanted parts of a leaf, with the item and without it: only the smaller part is counted."""
        if not any(want):
            return [None, None]
        has = self.columns[item][leaf.rows]
        parts = [leaf.rows[has], leaf.rows[~has]]
        less = len(parts[1]) < len(parts[0])
        one = self.columns[target][parts[less]]
        n1j = self._ones(parts[less][one])
        nj = n1j + self._ones(parts[less][~one])
        got = [(nj, n1j), (leaf.nj - nj, leaf.n1j - n1j)]
        return [Leaf(*leaf.child(item, not i), *got[i != less], parts[i]) if want[i] else None for i in (0, 1)]

    def prefetch(self, paths) -> None:
        self.scans += 1

    def supports(self, masks: list[int]) -> list[int]:
        """Rows that contain each mask. Masks that differ in their lowest item alone share the rows with the others."""
        out = dict.fromkeys(masks, self.total)
        rest = n = None
        for m in sorted(masks, key=lambda m: (m & (m - 1), m)):
            if not m:
                continue
            if rest != m & (m - 1):
                rest = m & (m - 1)
                rows = self._containing(rest)
                n = self.n[rows]
            out[m] = int(n[self.columns[(m & -m).bit_length() - 1][rows]].sum())
        return [out[m] for m in masks]

    def _containing(self, mask: int) -> np.ndarray | slice:
        """Numbers of the rows with all items of a mask."""
        if not mask:
            return slice(None)
        found = np.ones(len(self.n), bool)
        for w, v in enumerate(masks_to_words([mask], self.k)[0]):
            if v:
                found &= (self.words[:, w] & v) == v
        return np.flatnonzero(found)


class SparkCounts:
    """Counts by jobs over the compact DataFrame, a wave of paths at a time. Every job reads it again: it should be cheap to
    read, as the stored rows of counts_of."""

    def __init__(self, ct: DataFrame, k: int):
        self.ct, self.k, self.kept, self.scans = ct, k, {}, 0
        self.ahead = max(2, min(AHEAD, AHEAD_BYTES // (8 * (k + 1) ** 2)))
        self.total = int(ct.agg(F.sum("n")).first()[0] or 0)

    def prefetch(self, paths) -> None:
        """Count all paths that are not known yet, in one job per WAVE_BYTES of matrices."""
        need = [p for p in dict.fromkeys(paths) if p not in self.kept]
        most = max(1, WAVE_BYTES // (8 * (self.k + 1) ** 2))
        for at in range(0, len(need), most):
            self._count(need[at : at + most])

    def _count(self, paths) -> None:
        self.scans += 1
        k = self.k
        pos, neg = masks_to_words([p for p, _ in paths], k), masks_to_words([q for _, q in paths], k)

        def partial(batches):
            import pyarrow as pa

            sums: dict[int, np.ndarray] = {}
            for b in batches:
                words, n = _columns(b)
                for i in range(len(pos)):
                    rows = path_rows(words, pos[i], neg[i])
                    if rows.any():
                        sums[i] = sums.get(i, 0) + gram(words[rows], n[rows], k)
            if sums:
                yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([x.astype(np.int64).tobytes() for x in sums.values()], pa.binary())], names=["path", "gram"])

        def total(batches):
            import pyarrow as pa

            sums: dict[int, np.ndarray] = {}
            for b in batches:
                for i, x in zip(b.column("path").to_pylist(), b.column("gram").to_pylist(), strict=True):
                    sums[i] = sums.get(i, 0) + np.frombuffer(x, np.int64)
            if sums:
                yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([x.tobytes() for x in sums.values()], pa.binary())], names=["path", "gram"])

        schema = "path int, gram binary"
        got = self.ct.mapInArrow(partial, schema).repartition("path").mapInArrow(total, schema).collect()  # paths x K x K numbers
        for p in paths:
            self.kept[p] = np.zeros((k + 1, k + 1), np.int64)
        for r in got:
            self.kept[paths[r["path"]]] = np.frombuffer(r["gram"], np.int64).reshape(k + 1, k + 1)

    def path(self, pos: int, neg: int, target: int):
        if (pos, neg) not in self.kept:
            self.prefetch([(pos, neg)])
        g = self.kept[pos, neg]
        return int(g[-1, -1]), int(g[target, -1]), g[: self.k, -1], g[target, : self.k]

    def root(self, target: int) -> Leaf:
        return Leaf(*self.path(0, 0, target))

    def split(self, leaf: Leaf, target: int, item: int, pos: int, neg: int, want) -> list[Leaf | None]:
        """The wanted parts of the leaf at (pos, neg), with the item and without it."""
        paths = (pos | 1 << item, neg), (pos, neg | 1 << item)
        return [Leaf(*self.path(*p, target)) if w else None for p, w in zip(paths, want, strict=True)]

    def supports(self, masks: list[int]) -> list[int]:
        """Rows that contain each mask: one job; partial sums per partition."""
        self.scans += 1
        words = masks_to_words(masks, self.k)

        def count(batches):
            import pyarrow as pa

            sums = np.zeros(len(words), np.int64)
            for b in batches:
                w, n = _columns(b)
                for i in range(len(words)):
                    sums[i] += n[((w & words[i]) == words[i]).all(1)].sum()
            yield pa.RecordBatch.from_arrays([pa.array(np.flatnonzero(sums).astype(np.int32)), pa.array(sums[sums > 0])], names=["i", "c"])

        got = self.ct.mapInArrow(count, "i int, c long").groupBy("i").agg(F.sum("c").alias("c")).collect()
        out = [0] * len(masks)
        for r in got:
            out[r["i"]] = r["c"]
        return out


def _spread(rows: DataFrame) -> DataFrame:
    """Stored rows in pieces for all cores, stored again."""
    spark = rows.sparkSession
    path = scratch(spark, "spread")
    rows.repartition(2 * spark.sparkContext.defaultParallelism).write.parquet(path)
    return spark.read.parquet(path)


def stored(rows: DataFrame, name: str) -> DataFrame:
    """Rows made once, and written to the shared folder."""
    path = scratch(rows.sparkSession, name)
    rows.write.parquet(path)
    return rows.sparkSession.read.parquet(path)


def counts_of(ct: DataFrame, k: int, local_cells: int = LOCAL_CELLS, made: bool = False):
    """LocalCounts when the compact data have at most local_cells bits (their rows are counted first), else SparkCounts.
    The compact rows are made once, and written to the shared folder, unless ct is read from there (made)."""
    rows = ct.select(ct.columns[0], F.col("n").cast("long").alias("n"))
    rows = rows if made else stored(rows, "compact")
    if rows.count() * k > local_cells:
        return SparkCounts(_spread(rows), k)
    got = rows.toArrow().combine_chunks()
    batches = got.to_batches()
    if not batches:
        return LocalCounts(np.zeros((0, max(1, -(-k // 63))), np.uint64), np.zeros(0, np.int64), k)
    words, n = zip(*(_columns(b) for b in batches), strict=True)
    return LocalCounts(np.concatenate(words), np.concatenate(n), k)
