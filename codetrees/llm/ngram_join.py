"""Exact n-gram Jaccard join over count vectors in R-trees, and the components of its links.

A text's distinct 5-word shingles are hashed to 64 bits, whose top bits deal them into groups; the groups' counts are the
text's point. Sets of fewer than 2048 shingles have 256 groups, and each class of four times larger sets has four times
more; a set just above a limit also has a point of the class below, for partners there. For two texts the summed minima of their coordinates bound the overlap from above, and an R-tree node,
which stores the coordinate maxima and the size range of its points, bounds it for all points below it. Counts are bytes;
what goes beyond 255 is summed as the point's excess, whose minimum joins the bound.

1. Texts with equal sets become one node: each task names one of them (by a 128-bit digest of the set), and one
   aggregation of these names finds the nodes of all tasks. Copies, however many, go no further.
2. The tree is spread over tasks by regions. Any two texts over the threshold share one of their first
   n - ceil(t n) + 1 shingles in a common order (the most frequent ones last), so a node lies in the regions of these
   shingles, and a pair that may link meets in one of them. Regions with equal members are one; regions of more than
   `block` nodes are cut by size range and hash into blocks. Each task bulk-loads one R-tree over the blocks it holds,
   with a root per block, and every pair that is verified comes out of a search of that tree.
3. The search has three rounds, as pairs are wanted that connect components, not all pairs of a group:
   "cover": the first node of a block that nothing covers yet asks for its neighbours, which then are covered: at most
   one pair a node and block. Nodes with other neighbours in their block stay open, all others are done there. "best":
   regions whose open nodes are in several components give the best pair of any two components, among up to THINNED
   members of each. "all": what is in several components still gives all pairs of different components, and this round is
   complete. In the last two, the members of a region's largest component need not ask, and nodes ask in all blocks whose
   size range they may link with; a pair that meets in many regions comes out of the first of them only, as far as the
   HOMES first regions of both nodes tell, which they carry.
4. After each round pairs are bounded once more by points of about as many groups as the texts have shingles, then
   verified on the shingle sets; linked components become one, by large-star and small-star steps on tables.

Edge rules: null and empty texts, or texts without words, have no shingles and link with nothing; texts shorter than n
words are one shingle; repeated rows link with each other; null ids take part and never name a component unless all its
ids are null; texts of any length are hashed in bounded pieces; an empty table gives an empty result; extra columns are
ignored. Equality of shingles is equality of 64-bit hashes, of sets that of 128-bit digests. The join yields components;
pairs inside one component are not listed.
"""

from __future__ import annotations

import hashlib
import math
import zlib
from fractions import Fraction

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codetrees.llm.common import RID, dropped, keyed, mix64, release, tidy, written
from codetrees.llm.components import label_components
from codetrees.llm.textbytes import byte_columns, shingles

GROUPS, LARGE = 256, 2048  # groups of the smallest class of sets, and its limit
COUNTED = 3_000_000  # shingles counted together in a task
NAMED = 500_000  # sets that a task remembers to name copies; a forgotten one is named again
BROADCAST_IDS = 1_000_000  # 8 MB of row numbers
ROUNDS = ("cover", "best", "all")  # which pairs of a region come out; later rounds see what is still apart
THINNED = 48  # members of a component that take part in the second round of a region, about
FREQUENT, LISTED = 500, 100_000  # shingles in more than one of so many texts come last in the order; at most so many of them
LEAF, FAN = 8, 8  # points of a leaf, children of a node
BLOCK = 1024  # nodes of a region that are searched together
HOMES = 16  # first regions of a node that travel with it, to tell in which one a pair comes out
LOADED = 10 << 20  # bytes of points in one tree, about
BOUNDS = 8 << 20  # bytes of bounds computed at once
PAIRS_A_TASK = 1000  # pairs of one text that are verified together


def needed_overlap(n, m, t: Fraction):
    """Least overlap of sets of n and m shingles with Jaccard >= t."""
    p, q = t.numerator, t.denominator
    return -(-p * (n + m) // (p + q))


def prefix_length(n: int, t: Fraction) -> int:
    return n - -(-t.numerator * n // t.denominator) + 1 if n else 0


def count_vector(s: np.ndarray, bits: int = 8) -> tuple[np.ndarray, int]:
    """The point of a shingle set: counts of its shingles by group, cut at 255, and the sum of what was cut off."""
    c = np.bincount((s >> np.uint64(64 - bits)).astype(np.int64), minlength=1 << bits)
    return np.minimum(c, 255).astype(np.uint8), int(np.maximum(c - 255, 0).sum())


def size_class(n: int) -> int:
    return 0 if n < LARGE else ((n // LARGE).bit_length() + 1) // 2


def points_of(s: np.ndarray, t: Fraction) -> list[dict]:
    """The points of a set: of its class, and of the class of the smallest set that it may link with."""
    own, below = size_class(len(s)), size_class(-(-t.numerator * len(s) // t.denominator))
    out = []
    for c in {own, below}:
        point, excess = count_vector(s, 8 + 2 * c)
        out.append({"cls": c, "point": zlib.compress(point.tobytes(), 1), "excess": excess})
    return out


def fine_vector(s: np.ndarray) -> bytes:
    """A point of n to 2n groups, but 256 at least, with its excess in front."""
    c, excess = count_vector(s, max(8, len(s).bit_length()))
    return np.int64(excess).tobytes() + c.tobytes()


def fine_bound(a: bytes, b: bytes) -> int:
    """Upper bound of the overlap from two fine points; the finer one is folded to the groups of the other."""
    x, y = np.frombuffer(a, np.uint8, offset=8), np.frombuffer(b, np.uint8, offset=8)
    if len(x) > len(y):
        x = x.reshape(len(y), -1).sum(1)
    elif len(y) > len(x):
        y = y.reshape(len(x), -1).sum(1)
    return int(np.minimum(x, y).sum()) + min(int(np.frombuffer(a, np.int64, 1)[0]), int(np.frombuffer(b, np.int64, 1)[0]))


def overlap(a: np.ndarray, b: np.ndarray) -> int:
    """Size of the intersection of two sorted sets."""
    if len(a) > len(b):
        a, b = b, a
    if not len(a):
        return 0
    at = np.searchsorted(b, a)
    at[at == len(b)] = len(b) - 1
    return int((b[at] == a).sum())


def _runs(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and lengths of runs of equal values."""
    start = np.flatnonzero(np.concatenate([[True], values[1:] != values[:-1]])) if len(values) else np.zeros(0, np.int64)
    return start, np.diff(np.append(start, len(values)))


def _ranges(low: np.ndarray, size: np.ndarray) -> np.ndarray:
    """All of low[i] .. low[i] + size[i] - 1, one after the other."""
    return np.repeat(low - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))


class CountRTree:
    """Bulk-loaded R-tree over count vectors with one root per block: nodes hold coordinate maxima and size range."""

    def __init__(self, points: np.ndarray, sizes: np.ndarray, excess: np.ndarray, block: np.ndarray | None = None, leaf: int = LEAF, fan: int = FAN):
        self.points, self.sizes, self.excess = points, sizes.astype(np.int64), excess.astype(np.int64)
        block = np.zeros(len(sizes), np.int64) if block is None else block
        # Packing order: by size class, then by the coordinates that spread most, so that near copies share leaves.
        spread = np.argsort(-points.astype(np.float32).var(0))[:6] if len(points) else []
        self.order = np.lexsort((*(points[:, c] for c in spread), np.log2(np.maximum(self.sizes, 1)).astype(np.int8), block))
        of, start, size = block[self.order], *_runs(block[self.order])
        self.blocks = of[start]
        x, low, high, more = points[self.order], self.sizes[self.order], self.sizes[self.order], self.excess[self.order]
        self.first, self.count, self.is_leaf, maxima, lows, highs, mores = [], [], [], [], [], [], []
        self.root = np.full(len(start), -1)
        base, width, below = 0, leaf, 0
        while (self.root < 0).any():
            pieces = -(-size // width)
            at = np.repeat(start, pieces) + width * _ranges(np.zeros(len(start), np.int64), pieces)
            n = np.minimum(width, np.repeat(start + size, pieces) - at)
            x, low, high, more = (f.reduceat(v, at, axis=0) for f, v in ((np.maximum, x), (np.minimum, low), (np.maximum, high), (np.maximum, more)))
            self.first.append(at + below)
            self.count.append(n)
            self.is_leaf.append(np.full(len(at), base == 0))
            for kept, v in ((maxima, x), (lows, low), (highs, high), (mores, more)):
                kept.append(v)
            start, size, width = np.cumsum(pieces) - pieces, pieces, fan
            self.root = np.where((self.root < 0) & (pieces == 1), base + start, self.root)
            below, base = base, base + len(at)
        if self.first:
            self.first, self.count, self.is_leaf, self.most, self.least_size, self.most_size, self.most_excess = (np.concatenate(v) for v in (self.first, self.count, self.is_leaf, maxima, lows, highs, mores))

    def search(self, point: np.ndarray, size: int, excess: int, t: Fraction) -> np.ndarray:
        """Indices of points of the first block whose size and bound allow Jaccard >= t with the query."""
        return self.search_all(point[None], np.array([size]), np.array([excess]), self.blocks[:1], t)[1]

    def search_all(self, point: np.ndarray, size: np.ndarray, excess: np.ndarray, block: np.ndarray, t: Fraction) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Queries (row by row) against their blocks: (query, index of a point, surplus of its bound) of all points whose
        size and bound allow Jaccard >= t."""
        out = [np.zeros((3, 0), np.int64)]
        root = np.searchsorted(self.blocks, block) if len(self.sizes) else np.zeros(0, np.int64)
        query = np.flatnonzero(np.append(self.blocks, -1)[root] == block) if len(self.sizes) else np.zeros(0, np.int64)
        todo = [(query, self.root[root[query]])] if len(query) else []
        size, excess = size.astype(np.int64), excess.astype(np.int64)
        step = max(1, BOUNDS // max(1, self.points.shape[1]))

        def reach(q, least, most):
            return (most * t.denominator >= size[q] * t.numerator) & (size[q] * t.denominator >= least * t.numerator)

        while todo:
            q, node = todo.pop()
            if len(q) > step:
                todo += [(q[step:], node[step:])]
                q, node = q[:step], node[:step]
            ok = reach(q, self.least_size[node], self.most_size[node])
            q, node = q[ok], node[ok]
            bound = np.minimum(self.most[node], point[q]).sum(1, dtype=np.uint32) + np.minimum(self.most_excess[node], excess[q])
            ok = bound >= needed_overlap(size[q], np.maximum(self.least_size[node], -(-size[q] * t.numerator // t.denominator)), t)
            q, node = q[ok], node[ok]
            if not len(q):
                continue
            leaf = self.is_leaf[node]
            for part in (~leaf, leaf):
                if not part.any():
                    continue
                n = self.count[node[part]]
                q2, child = np.repeat(q[part], n), _ranges(self.first[node[part]], n)
                if part is not leaf:
                    todo.append((q2, child))
                    continue
                child = self.order[child]
                ok = reach(q2, self.sizes[child], self.sizes[child])
                q2, child = q2[ok], child[ok]
                for a in range(0, len(q2), step):
                    i, j = q2[a : a + step], child[a : a + step]
                    spare = np.minimum(self.points[j], point[i]).sum(1, dtype=np.uint32) + np.minimum(self.excess[j], excess[i]) - needed_overlap(size[i], self.sizes[j], t)
                    ok = spare >= 0
                    out.append(np.stack([i[ok], j[ok], spare[ok]]))
        return tuple(np.concatenate(out, 1))


def _sets(batch, column: str, k: int):
    data, off = byte_columns(batch.column(column))
    for i in range(batch.num_rows):
        yield shingles(data[off[i] : off[i + 1]], k)


def _parts(batches, most_bytes: int = 8 << 20, column: str = "text"):
    """Arrow batches in slices of bounded text."""
    for b in batches:
        at = 0
        while at < b.num_rows:
            _, off = byte_columns(b.column(column).slice(at))
            size = max(1, int(np.searchsorted(off - off[0], most_bytes, "right")) - 1)
            yield b.slice(at, size)
            at += size


def _frequent(k: int):
    """Pass 1: shingles that are frequent among some texts, with their counts; copies count once."""

    def run(batches):
        import pyarrow as pa

        held: dict[bytes, np.ndarray] = {}

        def frequent():
            u, c = np.unique(np.concatenate(list(held.values())), return_counts=True)
            many = c >= max(3, len(held) // FREQUENT)
            return pa.RecordBatch.from_arrays([pa.array(u[many].view(np.int64)), pa.array(c[many].astype(np.int64))], names=["key", "n"])

        size = 0
        for b in _parts(batches):
            for s in _sets(b, "text", k):
                name = hashlib.blake2b(s, digest_size=16).digest()
                if len(s) and name not in held:
                    held[name] = s
                    size += len(s)
            if size > COUNTED:
                yield frequent()
                held, size = {}, 0
        if held:
            yield frequent()

    return run


def _describe(t: Fraction, k: int, frequent: np.ndarray, rank: np.ndarray):
    """Pass 2: every text with its size and the first text of the task with the same set; these texts also with the
    digest of their set, their points, and their prefix: shingles that are not frequent, and frequent ones."""

    def run(batches):
        import pyarrow as pa

        named: dict[bytes, int] = {}
        points = pa.list_(pa.struct([("cls", pa.int32()), ("point", pa.binary()), ("excess", pa.int64())]))
        kinds = [pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary(), points, pa.binary()]
        for b in _parts(batches):
            rids, rows = b.column(RID).to_pylist(), []
            if len(named) > NAMED:
                named = {}
            for rid, s in zip(rids, _sets(b, "text", k), strict=True):
                n = len(s)
                digest = hashlib.blake2b(s, digest_size=16).digest()
                to = named.setdefault(digest, rid) if n else rid
                if not n or to != rid:
                    rows.append((n, to, *[None] * 5))
                    continue
                p = prefix_length(n, t)
                at = np.searchsorted(frequent, s)
                common = np.zeros(n, bool)
                if len(frequent):
                    at[at == len(frequent)] = 0
                    common = frequent[at] == s
                rare, late = s[~common][:p], s[:0]
                if len(rare) < p:
                    late = s[common]
                    late = late[np.argsort(rank[at[common]], kind="stable")][: p - len(rare)]
                rows.append((n, to, digest, rare.tobytes(), late.tobytes(), points_of(s, t), zlib.compress(fine_vector(s), 1)))
            yield pa.RecordBatch.from_arrays([b.column(RID), *(pa.array([r[c] for r in rows], kind) for c, kind in enumerate(kinds))], names=[RID, "n", "first", "digest", "rare", "late", "points", "fine"])

    return run


def _deal_keys(buckets: int):
    """Prefix shingles that are not frequent, dealt to buckets as blobs of (32-bit key, rid)."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            for lo in range(0, b.num_rows, 4000):
                part = b.slice(lo, 4000)
                data, off = byte_columns(part.column("rare"))
                keys = mix64(np.frombuffer(data[off[0] : off[-1]].tobytes(), np.uint64))
                rids = np.repeat(part.column(RID).to_numpy(), np.diff(off) // 8)
                bucket = ((keys >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64)
                order = np.argsort(bucket, kind="stable")
                bucket, small, rids = bucket[order], keys[order].astype(np.uint32), rids[order]
                start, size = _runs(bucket)
                spans = list(zip(start, start + size, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array([int(bucket[a]) for a, _ in spans], pa.int32()), pa.array([small[a:z].tobytes() for a, z in spans], pa.binary()), pa.array([rids[a:z].astype(np.int64).tobytes() for a, z in spans], pa.binary())], names=["bucket", "keys", "rids"])

    return run


def _regions(batches):
    """Per bucket: nodes that share a key, as (g, rid); a region is named by the hash of its members, so that equal
    regions of many keys are one."""
    import pyarrow as pa

    held: dict[int, list] = {}
    for b in batches:
        for bucket, keys, rids in zip(b.column("bucket").to_pylist(), b.column("keys").to_pylist(), b.column("rids").to_pylist(), strict=True):
            held.setdefault(bucket, []).append((keys, rids))
    while held:
        _, blobs = held.popitem()
        key = np.concatenate([np.frombuffer(x, np.uint32) for x, _ in blobs])
        rid = np.concatenate([np.frombuffer(x, np.int64) for _, x in blobs])
        del blobs
        order = np.lexsort((rid, key))
        key, rid = key[order], rid[order]
        keep = np.ones(len(key), bool)
        keep[1:] = (key[1:] != key[:-1]) | (rid[1:] != rid[:-1])
        key, rid = key[keep], rid[keep]
        start, size = _runs(key)
        name = np.add.reduceat(mix64(rid.view(np.uint64) + np.uint64(0x9E3779B97F4A7C15)), start) if len(start) else np.zeros(0, np.uint64)
        many = size > 1
        start, size, name = start[many], size[many], name[many]
        _, one = np.unique(name, return_index=True)
        start, size, name = start[one], size[one], name[one]
        for lo in range(0, len(start), 20_000):
            a, z, g = start[lo : lo + 20_000], size[lo : lo + 20_000], name[lo : lo + 20_000]
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(g, z).view(np.int64)), pa.array(rid[_ranges(a, z)])], names=["g", RID])


def _late_regions(batches):
    """Frequent prefix shingles: (g, rid) row by row, as their regions may be of any size."""
    import pyarrow as pa

    for b in batches:
        data, off = byte_columns(b.column("late"))
        keys = mix64(np.frombuffer(data[off[0] : off[-1]].tobytes(), np.uint64))
        if len(keys):
            yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(np.repeat(b.column(RID).to_numpy(), np.diff(off) // 8))], names=["g", RID])


NO_HOME = np.iinfo(np.int64).max


def home_rows(homes) -> np.ndarray:
    """An Arrow column of lists of region names, as sorted rows of HOMES names, filled up with NO_HOME."""
    size = np.diff(homes.offsets.to_numpy())
    out = np.full((len(size), HOMES), NO_HOME)
    out[np.repeat(np.arange(len(size)), size), _ranges(np.zeros(len(size), np.int64), size)] = homes.flatten().to_numpy()
    return out


class Blocks:
    """Rows of some whole blocks: rid, comp, n, point, excess, ask, asked, top as columns, and the number of the block.
    The rows that are asked make the tree. homes: the first regions of each row, and region: the one it is in here."""

    def __init__(self, cols: list[np.ndarray], block: np.ndarray, t: Fraction, homes: np.ndarray | None = None, region: np.ndarray | None = None):
        self.rid, self.comp, self.n, self.point, self.excess, self.ask, asked, self.top = cols
        self.block, self.t, self.homes, self.region = block, t, homes, region
        self.at = np.flatnonzero(asked)
        self.tree = CountRTree(self.point[self.at], self.n[self.at], self.excess[self.at], block[self.at])

    def _search(self, some: np.ndarray) -> np.ndarray:
        q, j, spare = self.tree.search_all(self.point[some], self.n[some], self.excess[some], self.block[some], self.t)
        return np.stack([some[q], self.at[j], spare])

    def covers(self) -> tuple[np.ndarray, np.ndarray]:
        """In waves, the first uncovered row of every block covers its uncovered neighbours: pairs (row, row, surplus);
        and which rows have other neighbours."""
        order = np.lexsort((self.rid, self.block))
        covered, out = np.zeros(len(order), bool), []
        while len(order):
            start, size = _runs(self.block[order])
            pivots = order[start[size > 1]]
            covered[order[start]] = True
            i, j, spare = self._search(pivots) if len(pivots) else np.zeros((3, 0), np.int64)
            fresh = ~covered[j]
            out.append(np.stack([i, j, spare])[:, fresh])
            covered[j] = True
            order = order[~covered[order]]
        out = np.concatenate(out, 1) if out else np.zeros((3, 0), np.int64)
        by = np.full(len(covered), -1)
        by[out[1]] = out[0]
        other = np.zeros(len(covered), bool)
        for a in range(0, len(covered), 2048):
            i, j, _ = self._search(np.arange(a, min(a + 2048, len(covered))))
            left = (i != j) & (by[i] != j) & (by[j] != i)
            other[i[left]] = other[j[left]] = True
        return out, other

    def crossing(self, best: bool) -> np.ndarray:
        """Pairs of different components; with best, the best one of any two components."""
        out, asking = [np.zeros((3, 0), np.int64)], np.flatnonzero(self.ask)
        for a in range(0, len(asking), 2048):
            p = self._search(asking[a : a + 2048])
            i, j = p[:2]
            p = p[:, (self.comp[i] != self.comp[j]) & (self.top[j] | (self.rid[i] < self.rid[j]))]
            p = p if self.homes is None else p[:, self._at_home(p[0], p[1])]
            out.append(self._best(p) if best else p)
        p = np.concatenate(out, 1)
        return self._best(p) if best else p

    def _at_home(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Whether this region is the first that both rows are in. As homes are the least names of each row's regions, the
        least name in both homes is the first common region; where homes have none in common, every region counts."""
        out = np.ones(len(i), bool)
        for a in range(0, len(i), 1 << 16):
            x, y = self.homes[i[a : a + (1 << 16)]], self.homes[j[a : a + (1 << 16)]]
            first = np.full(len(x), NO_HOME)
            for c in range(HOMES):
                first = np.minimum(first, np.where((y == x[:, c : c + 1]).any(1), x[:, c], NO_HOME))
            out[a : a + (1 << 16)] = (first == NO_HOME) | (first == self.region[i[a : a + (1 << 16)]])
        return out

    def _best(self, p: np.ndarray) -> np.ndarray:
        x, y = self.comp[p[0]], self.comp[p[1]]
        low, high = np.minimum(x, y), np.maximum(x, y)
        order = np.lexsort((self.rid[p[1]], self.rid[p[0]], -p[2], high, low))
        low, high = low[order], high[order]
        return p[:, order[np.concatenate([[True], (low[1:] != low[:-1]) | (high[1:] != high[:-1])])]] if len(low) else p


def _pairs(t: Fraction, mode: str):
    """Sorted by class and block: pairs out of R-trees over some blocks at a time; in "cover" also open nodes (g, a)."""

    def run(batches):
        import pyarrow as pa

        def made(*cols):
            k = next(len(c) for c in cols if c is not None)
            return pa.RecordBatch.from_arrays([pa.nulls(k, pa.int64()) if c is None else pa.array(c.astype(np.int64)) for c in cols], names=["g", "a", "b", "ca", "cb", "spare"])

        def found(cols, names):
            *cols, homes = cols
            b = Blocks(cols, np.cumsum(np.concatenate([[False], (np.diff(names, axis=0) != 0).any(1)])), t, None if mode == "cover" else homes, names[:, 1])
            if mode == "cover":
                (i, j, spare), other = b.covers()
                yield made(names[other, 1], b.rid[other], None, None, None, None)
            else:
                i, j, spare = b.crossing(mode == "best")
            yield made(None, b.rid[i], b.rid[j], b.comp[i], b.comp[j], spare)

        def whole(held):
            return [np.concatenate(x) for x in zip(*(h[0] for h in held), strict=True)], np.concatenate([h[1] for h in held])

        held, size = [], 0
        for batch in batches:
            for a, z in zip(*_runs(batch.column("cls").to_numpy()), strict=True):
                b = batch.slice(a, z)
                groups = GROUPS << 2 * b.column("cls")[0].as_py()
                point = np.frombuffer(b"".join(map(zlib.decompress, b.column("point").to_pylist())), np.uint8).reshape(-1, groups)
                cols = [*(b.column(c).to_numpy() for c in (RID, "comp", "n")), point, b.column("excess").to_numpy(), *(b.column(c).to_numpy(zero_copy_only=False) for c in ("ask", "asked", "top")), home_rows(b.column("homes")) if mode != "cover" else np.zeros((len(point), 0), np.int64)]
                if held and held[0][0][3].shape[1] != groups:
                    yield from found(*whole(held))
                    held, size = [], 0
                held.append((cols, np.stack([b.column(c).to_numpy() for c in ("cls", "g", "band", "sub", "chunk")], 1)))
                size += point.nbytes
                if size < LOADED:
                    continue
                cols, names = whole(held)
                before = np.flatnonzero((names != names[-1]).any(1))  # the last block may go on
                cut = int(before[-1]) + 1 if len(before) else 0
                if cut:
                    yield from found([c[:cut] for c in cols], names[:cut])
                held, size = [([c[cut:] for c in cols], names[cut:])], 0
        if held:
            yield from found(*whole(held))

    return run


def _finer(t: Fraction):
    """Pairs whose fine points let them through, the larger text first."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            cols = [b.column(c).to_pylist() for c in ("na", "nb", "fa", "fb")]
            keep = pa.array([fine_bound(zlib.decompress(x), zlib.decompress(y)) >= needed_overlap(n, m, t) for n, m, x, y in zip(*cols, strict=True)], pa.bool_())
            turned = np.array(cols[0]) < np.array(cols[1])
            both = lambda x, y, b=b, turned=turned, keep=keep: pa.array(np.where(turned, b.column(y).to_numpy(), b.column(x).to_numpy())).filter(keep)
            yield pa.RecordBatch.from_arrays([both("a", "b"), both("b", "a"), both("ca", "cb"), both("cb", "ca")], names=["a", "b", "ca", "cb"])

    return run


def _closer(pairs: DataFrame, fine: DataFrame, t: Fraction) -> DataFrame:
    """Pairs that the finer points let through."""
    both = pairs.join(fine.select(F.col(RID).alias("a"), F.col("n").alias("na"), F.col("fine").alias("fa")), "a").join(fine.select(F.col(RID).alias("b"), F.col("n").alias("nb"), F.col("fine").alias("fb")), "b")
    return written(both.select("a", "b", "ca", "cb", "na", "nb", "fa", "fb").mapInArrow(tidy(_finer(t)), "a long, b long, ca long, cb long"), "closer")


def _make_sets(k: int):
    def run(batches):
        import pyarrow as pa

        for b in _parts(batches):
            yield pa.RecordBatch.from_arrays([b.column(RID), pa.array([s.tobytes() for s in _sets(b, "text", k)], pa.binary())], names=[RID, "s"])

    return run


def _compared(t: Fraction):
    """Sorted by a, turn and kind: the set of a (kind 0), then its pairs with the sets of their b (kind 1)."""

    def run(batches):
        import pyarrow as pa

        own, of = None, None
        for b in batches:
            keep = []
            for a, kind, s in zip(b.column("a").to_pylist(), b.column("kind").to_pylist(), b.column("s"), strict=True):
                x = np.frombuffer(s.as_buffer(), np.uint64)
                if kind == 0:
                    own, of = x.copy(), a
                keep.append(kind == 1 and of == a and overlap(own, x) >= needed_overlap(len(own), len(x), t))
            keep = pa.array(keep, pa.bool_())
            yield pa.RecordBatch.from_arrays([b.column(c).filter(keep) for c in ("a", "b", "ca", "cb")], names=["a", "b", "ca", "cb"])

    return run


def _composed(labels: DataFrame, new: DataFrame) -> DataFrame:
    """Labels of nodes after their labels have got new ones."""
    now = labels.join(new.select(F.col("node").alias("label"), F.col("label").alias("now")), "label", "left").select("node", F.coalesce("now", "label").alias("label"))
    return written(now.unionByName(new.join(labels, "node", "left_anti")), "labels")


def _verify(pairs: DataFrame, fine: DataFrame, docs: DataFrame, t: Fraction, k: int) -> DataFrame:
    """Pairs whose shingle sets reach the threshold. A set travels once to every PAIRS_A_TASK of the pairs in which its
    text comes first, and once to each in which it comes second."""
    if pairs.isEmpty():
        return pairs
    pairs = _closer(pairs, fine, t)
    need = written(pairs.select(F.col("a").alias(RID)).unionByName(pairs.select(F.col("b").alias(RID))).distinct(), "need")
    few = need.count() <= BROADCAST_IDS  # else the texts are shuffled to their numbers
    sets = written(docs.join(F.broadcast(need) if few else need, RID, "left_semi").mapInArrow(tidy(_make_sets(k)), f"{RID} long, s binary"), "sets")
    turns = pairs.groupBy("a").agg(F.ceil(F.count("*") / PAIRS_A_TASK).cast("int").alias("turns"))
    dealt = pairs.join(turns, "a").withColumn("turn", F.pmod(F.xxhash64("b"), F.col("turns")).cast("int"))
    second = dealt.join(sets.withColumnRenamed(RID, "b"), "b").select("a", "turn", F.lit(1).alias("kind"), "b", "ca", "cb", "s")
    none = F.lit(None).cast("long")
    first = sets.withColumnRenamed(RID, "a").join(turns, "a").select("a", F.explode(F.sequence(F.lit(0), F.col("turns") - 1)).alias("turn"), F.lit(0).alias("kind"), none.alias("b"), none.alias("ca"), none.alias("cb"), "s")
    both = second.unionByName(first).repartition("a", "turn").sortWithinPartitions("a", "turn", "kind")
    out = written(both.mapInArrow(tidy(_compared(t)), "a long, b long, ca long, cb long"), "verified")
    dropped(pairs, sets, need)
    return out


def _placed(regions: DataFrame, points: DataFrame, t: Fraction, block: int) -> DataFrame:
    """Members of regions, by class of sizes, with two nodes at least: cls, g, rid, own band (of sizes) and sub of a
    region with more than `block` members, else 0, 0; and the number of subs of the band. Linked texts are at most one
    band apart."""
    width = -math.log(float(t)) * (1 + 1e-9) if t < 1 else 1e-9
    sized = regions.join(points.select(RID, "cls", F.floor(F.log("n") / width).cast("int").alias("band")), RID)
    m = sized.groupBy("cls", "g").agg(F.count("*").alias("m")).where("m > 1")
    sized = sized.join(m, ["cls", "g"]).select("cls", "g", RID, (F.col("m") > block).alias("big"), F.when(F.col("m") > block, F.col("band")).otherwise(0).alias("band"))
    subs = sized.where("big").groupBy("cls", "g", "band").agg(F.ceil(F.count("*") / block).cast("int").alias("subs"))
    out = sized.join(subs, ["cls", "g", "band"], "left").withColumn("subs", F.coalesce("subs", F.lit(1)))
    return out.select("cls", "g", RID, "big", "band", F.pmod(F.xxhash64(RID), F.col("subs")).cast("int").alias("sub"), "subs")


def _mixed(members: DataFrame, labels: DataFrame) -> DataFrame:
    """Members of regions that hold more than one component still, with their components' present labels."""
    now = members.join(labels.select(F.col("node").alias("comp"), "label"), "comp", "left").withColumn("comp", F.coalesce("label", "comp")).drop("label")
    several = now.groupBy("cls", "g").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select("cls", "g")
    return now.join(several, ["cls", "g"], "left_semi")


def _thinned(members: DataFrame) -> DataFrame:
    """About THINNED members of each component of each region."""
    size = members.groupBy("cls", "g", "comp").agg(F.count("*").alias("c")).where(F.col("c") > THINNED)
    one_in = F.ceil(F.coalesce("c", F.lit(1)) / THINNED).cast("int")
    return members.join(size, ["cls", "g", "comp"], "left").where(F.pmod(F.xxhash64(RID, "g"), one_in) == 0).drop("c")


def _homes(members: DataFrame) -> DataFrame:
    """The HOMES first regions of every node that is in several, by class."""
    return members.groupBy(RID, "cls").agg(F.slice(F.array_sort(F.collect_set("g")), 1, HOMES).alias("homes")).where(F.size("homes") > 1)


def _seated(members: DataFrame, cover: bool, block: int) -> DataFrame:
    """Members in the blocks where they ask or are asked: block key, rid, comp, ask, asked, top."""
    yes, no, zero = F.lit(True), F.lit(False), F.lit(0)
    if cover:
        return members.select("cls", "g", "band", "sub", zero.alias("chunk"), RID, "comp", yes.alias("ask"), yes.alias("asked"), no.alias("top"))
    counts = members.groupBy("cls", "g", "comp").agg(F.count("*").alias("c")).groupBy("cls", "g")
    chunks = F.greatest(F.lit(1), F.ceil((F.sum("c") - F.max("c")) / (8 * block)).cast("int"))
    known = members.join(counts.agg(F.max_by("comp", F.struct("c", "comp")).alias("largest"), chunks.alias("chunks")), ["cls", "g"]).withColumn("top", F.col("comp") == F.col("largest"))
    small = known.where("not big").select("cls", "g", "band", "sub", zero.alias("chunk"), RID, "comp", (~F.col("top")).alias("ask"), yes.alias("asked"), "top")
    big = known.where("big")
    asked = big.select("cls", "g", "band", "sub", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"), RID, "comp", no.alias("ask"), yes.alias("asked"), "top")
    subs = big.groupBy("cls", "g", "band").agg(F.max("subs").alias("subs"))
    askers = big.where("not top").withColumn("chunk", F.pmod(F.xxhash64(RID, F.lit(7)), F.col("chunks")).cast("int")).drop("subs")
    askers = askers.withColumn("band", F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1))).join(subs, ["cls", "g", "band"])
    askers = askers.select("cls", "g", "band", F.explode(F.sequence(F.lit(0), F.col("subs") - 1)).alias("sub"), "chunk", RID, "comp", yes.alias("ask"), no.alias("asked"), "top")
    return small.unionByName(asked).unionByName(askers)


def similarity_links(docs: DataFrame, t: Fraction, k: int, block: int = BLOCK) -> tuple[DataFrame, DataFrame]:
    """docs: RID, text -> (one row per text: RID, n, comp), (label of comps: node, label). Texts are connected by links
    of Jaccard >= t exactly when the labels of their comps are equal (a comp without a row is its own label)."""
    spark = docs.sparkSession
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    often = docs.mapInArrow(tidy(_frequent(k)), "key long, n long").groupBy("key").agg(F.sum("n").alias("n"))
    floor = max(20, docs.count() // FREQUENT)
    heavy = often.where(F.col("n") >= floor).orderBy(F.desc("n"), "key").limit(LISTED).collect()  # order only
    frequent = np.array([r["key"] for r in heavy], np.int64).view(np.uint64)
    counts = np.array([r["n"] for r in heavy], np.int64)
    order = np.argsort(frequent)
    frequent, counts = frequent[order], counts[order]

    texts = written(docs.mapInArrow(tidy(_describe(t, k, frequent, counts)), f"{RID} long, n long, first long, digest binary, rare binary, late binary, points array<struct<cls int, point binary, excess long>>, fine binary"), "texts")
    named = texts.where("digest is not null").select(RID, "n", "digest")
    equal = named.groupBy("n", "digest").agg(F.min(RID).alias("comp"))  # a row per task and set at most goes in
    equal = written(named.join(equal, ["n", "digest"]).select(RID, "comp"), "equal")
    comps = written(texts.select(RID, "n", "first").join(equal.withColumnRenamed(RID, "first"), "first", "left").select(RID, "n", F.coalesce("comp", "first").alias("comp")), "comps")
    fine = texts.where("digest is not null").select(RID, "n", "fine")
    points = texts.where("digest is not null").select(RID, "n", F.inline("points"))
    nodes = texts.where("digest is not null").join(equal.where(F.col(RID) == F.col("comp")).select(RID), RID, "left_semi")

    total = texts.agg(F.sum(F.octet_length("rare"))).first()[0] or 0
    buckets = max(parts, -(-total // 8 // 4_000_000))
    dealt = nodes.select(RID, "rare").mapInArrow(tidy(_deal_keys(buckets)), "bucket int, keys binary, rids binary").repartition(buckets, "bucket")
    regions = dealt.mapInArrow(tidy(_regions), f"g long, {RID} long").distinct().unionByName(nodes.where("octet_length(late) > 0").select(RID, "late").mapInArrow(tidy(_late_regions), f"g long, {RID} long"))
    regions = written(regions, "regions")
    members = written(_placed(regions, points, t, block).withColumn("comp", F.col(RID)), "members")
    dropped(regions)
    del dealt, nodes
    release(spark)
    tried, labels, found, done = None, label_components(equal.limit(0).select(F.col(RID).alias("a"), F.col("comp").alias("b"))), None, []
    key = ["cls", "g", "band", "sub", "chunk"]
    for mode in ROUNDS:
        if found is not None and not found.isEmpty():
            new = label_components(found.select(F.col("ca").alias("a"), F.col("cb").alias("b")))
            left, both = written(_mixed(members, new), "members"), _composed(labels, new)
            dropped(members, labels, new)
            members, labels = left, both
        part = _thinned(members) if mode == "best" else members
        full = _seated(part, mode == "cover", block).join(points, [RID, "cls"])
        if mode != "cover":
            full = full.join(_homes(part), [RID, "cls"], "left").withColumn("homes", F.coalesce("homes", F.array().cast("array<long>")))
        full = full.repartition(*key).sortWithinPartitions(*key)
        pairs = full.mapInArrow(tidy(_pairs(t, mode)), "g long, a long, b long, ca long, cb long, spare long")
        if mode == "cover":
            pairs = written(pairs, "covers")
            done.append(pairs)
            still = pairs.where("b is null").select("g", F.col("a").alias(RID))
            left = written(members.where("not big").join(still, ["g", RID], "left_semi").unionByName(members.where("big")), "members")
            dropped(members)
            members = left
        pairs = pairs.where("b is not null").drop("g")
        if mode == "best":
            low, high = F.least("ca", "cb"), F.greatest("ca", "cb")
            pairs = pairs.groupBy(low.alias("lo"), high.alias("hi")).agg(F.max_by(F.struct("a", "b", "ca", "cb"), F.struct("spare", "a", "b")).alias("p")).select("p.*")
        low, high = F.struct(F.col("a").alias("r"), F.col("ca").alias("c")), F.struct(F.col("b").alias("r"), F.col("cb").alias("c"))
        pairs = pairs.select(F.least(low, high).alias("x"), F.greatest(low, high).alias("y")).select(F.col("x.r").alias("a"), F.col("y.r").alias("b"), F.col("x.c").alias("ca"), F.col("y.c").alias("cb")).distinct()
        if tried is not None:
            pairs = pairs.join(tried, ["a", "b"], "left_anti")
        pairs = written(pairs, "pairs")
        tried = pairs.select("a", "b") if tried is None else tried.unionByName(pairs.select("a", "b"))
        found = _verify(pairs, fine, docs, t, k)
        done += [pairs, found]
        del full, part
        release(spark)
    if not found.isEmpty():
        new = label_components(found.select(F.col("ca").alias("a"), F.col("cb").alias("b")))
        both = _composed(labels, new)
        dropped(labels, new)
        labels = both
    dropped(texts, equal, members, *done)
    return comps, labels


def jaccard_components(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: Fraction = Fraction(3, 4), k: int = 5, row_col: str | None = None) -> DataFrame:
    """One row per input row: RID, id, n_shingles, component_id (least id reachable by links), representative (whether the
    row is the one of its component that stays: least id, then least RID)."""
    docs = keyed(df, id_col, [text_col], row_col).select(RID, F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    comps, labels = similarity_links(docs.select(RID, "text"), threshold, k)
    named = comps.join(labels.select(F.col("node").alias("comp"), "label"), "comp", "left").select(RID, "n", F.coalesce("label", "comp").alias("comp"))
    rows = named.join(docs.select(RID, "id"), RID)
    least = rows.groupBy("comp").agg(F.min(F.struct(F.col("id").isNull(), F.col("id"), F.col(RID))).alias("least"))
    rows = rows.join(least, "comp")
    return rows.select(RID, F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.col("least.id").alias("component_id"), (F.col(f"least.{RID}") == F.col(RID)).alias("representative"))


def op1_ngram_join(spark, sf_dir: str) -> DataFrame:
    """All documents, words of lower-cased A-Z text, Jaccard of 5-word shingles at least 0.75."""
    return jaccard_components(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop(RID, "representative")


OP1_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
     s AS MATERIALIZED (SELECT DISTINCT doc_id, list_aggregate(w[i:i + least(5, len(w)) - 1], 'string_agg', ' ') AS s
           FROM (SELECT doc_id, w, unnest(range(1, len(w) - least(5, len(w)) + 2)) AS i FROM w WHERE len(w) > 0)),
     n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
     p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS shared FROM s a JOIN s b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY 1, 2),
     l AS MATERIALIZED (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * shared >= 75 * (x.n + y.n - shared)),
     e AS MATERIALIZED (SELECT a, b FROM l UNION SELECT b, a FROM l),
     r(doc_id, c) AS (SELECT doc_id, doc_id FROM documents UNION SELECT e.b, r.c FROM r JOIN e ON e.a = r.doc_id)
SELECT r.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, min(r.c) AS component_id FROM r LEFT JOIN n USING (doc_id) GROUP BY ALL
"""
