"""Sequence packing by length patterns fitted with non-negative least squares.

One pass tokenizes each document once and cuts it into pieces; a piece knows its rank among its task's pieces of the
same length. Only the length histogram (at most `size` numbers) reaches the driver. There all patterns of up to three
lengths that fill a sequence exactly are enumerated, their repeat counts are fitted to the histogram by weighted
non-negative least squares, a share of them is rounded along the list of patterns, never beyond what is left of each
length, and the residual lengths are packed by best fit on the histogram. The share leaves the residual enough pieces of
all lengths to fill its sequences; of a few shares and places where the rounding starts, the best plan is taken. The plan is a list of rank ranges per length, and each piece finds its sequence and offset by its rank,
so no group of equal lengths ever meets in one task.

Edge rules: null or empty text is one piece holding only the end token; repeated rows are packed each; null ids are kept
as they are; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import re
import zlib

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codetrees.llm.common import small_batches, tidy, worker_cache, written

END_ID = 2
SIZE = 1024


class Encoder:
    """Ids of a byte-level BPE file of the `tokenizers` library. Texts of Latin letters and ASCII go through tiktoken,
    loaded from the same file's vocabulary, when both agree on trial texts; all others through `tokenizers` itself."""

    LATIN = re.compile("[^\x00-ɏ]")
    TRIAL = ["", " ", "a  b\n\n c\t", "I'll we've 12 3x!! | $%&*# \x1c\x85\xa0x", "Éa où ça: ñandú, größe; don'T\r\n  end ", "".join(map(chr, range(0x250))), " ".join(map(chr, range(0x250)))]

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.full = Tokenizer.from_file(path)
        self.special = [t.content for t in self.full.get_added_tokens_decoder().values()]
        self.fast = None
        try:
            import tiktoken
        except ImportError:
            return
        printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
        other = [b for b in range(256) if b not in printable]
        byte_of = {chr(b): b for b in printable} | {chr(256 + i): b for i, b in enumerate(other)}
        ranks = {bytes(byte_of[c] for c in t): i for t, i in self.full.get_vocab(with_added_tokens=False).items() if t not in self.special and all(c in byte_of for c in t)}
        pattern = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"  # fixed value: the byte-level splitter's pattern
        fast = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        if all(fast.encode_ordinary(t) == self._slow(t) for t in self.TRIAL):
            self.fast = fast.encode_ordinary

    def _slow(self, text: str) -> list[int]:
        return self.full.encode(text, add_special_tokens=False).ids

    def __call__(self, text: str) -> list[int]:
        if self.fast is None or self.LATIN.search(text) or any(s in text for s in self.special):
            return self._slow(text)
        return self.fast(text)


def encoder(path: str) -> Encoder:
    cache = worker_cache().setdefault("encoders", {})
    if path not in cache:
        cache[path] = Encoder(path)
    return cache[path]


def _pieces(path: str, size: int, end_id: int, with_ids: bool, id_type):
    def run(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        encode = encoder(path)
        pid = TaskContext.get().partitionId()
        used = np.zeros(size + 1, np.int64)
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                rows: list[list] = [[] for _ in range(8)]
                for doc, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    ids = np.array([*encode(text or ""), end_id], "<u4")
                    lo, hi, k = 0, (len(ids) % size or size), 0
                    while lo < len(ids):
                        x = ids[lo:hi]
                        for r, v in zip(rows, (doc, k, lo, len(x), zlib.crc32(x.tobytes()), pid, int(used[len(x)]), x.astype(np.int32)), strict=True):
                            r.append(v)
                        used[len(x)] += 1
                        lo, hi, k = hi, hi + size, k + 1
                kinds = [part.column(0).type, pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.list_(pa.int32())]
                n = 8 if with_ids else 7
                yield pa.RecordBatch.from_arrays([pa.array(r, t) for r, t in zip(rows[:n], kinds[:n], strict=True)], names=["id", "piece", "start", "length", "ids_crc32", "pid", "rank", "ids"][:n])

    return run


def patterns(lengths: np.ndarray, size: int) -> np.ndarray:
    """All multisets of two or three present lengths, summing to size exactly: rows of three, 0 for no third."""
    have = np.zeros(size + 1, bool)
    have[lengths[(lengths > 0) & (lengths < size)]] = True
    out = []
    for a in np.flatnonzero(have):
        if 2 * a <= size and have[size - a] and size - a >= a:
            out.append(np.array([[a, size - a, 0]]))
        b = np.flatnonzero(have)
        b = b[(b >= a) & (2 * b <= size - a)]
        b = b[have[size - a - b]]
        if len(b):
            out.append(np.stack([np.full(len(b), a), b, size - a - b], 1))
    return np.concatenate(out) if out else np.zeros((0, 3), np.int64)


def fit_counts(p: np.ndarray, hist: np.ndarray, rounds: int = 200) -> np.ndarray:
    """Non-negative least squares of pattern counts to the histogram by multiplicative steps; long lengths, which are
    harder to place, weigh more."""
    weight = np.arange(len(hist)) / (len(hist) - 1) + 0.1
    weight[0] = 0
    x = np.full(len(p), hist.sum() / max(1, 2 * len(p)))
    target = (weight * hist)[p].sum(1)
    for _ in range(rounds):
        made = np.bincount(p.ravel(), np.repeat(x, 3), len(hist))
        x *= target / np.maximum((weight * made)[p].sum(1), 1e-12)
    return x


SHARES = (0.3, 0.45, 0.6, 0.75)
STARTS = (0.05, 0.2, 0.35, 0.5, 0.65, 0.8, 0.95)


def round_counts(p: np.ndarray, x: np.ndarray, hist: np.ndarray, share: float = 0.5, start: float = 0.5) -> tuple[list[tuple[tuple[int, ...], int]], np.ndarray]:
    """Whole repeat counts whose running sums follow those of share * x from start on, never more than what is left of
    each length; and what is left."""
    left, out = hist.copy(), []
    counts = np.diff(np.floor(np.cumsum(x * share) + start).astype(np.int64), prepend=0)
    for i in np.flatnonzero(counts):
        parts = [int(v) for v in p[i] if v]
        n = min(int(counts[i]), *(int(left[v]) // parts.count(v) for v in parts))
        if n > 0:
            out.append((tuple(parts), n))
            for v in parts:
                left[v] -= n
    return out, left


def best_fit(left: np.ndarray, size: int) -> list[tuple[tuple[int, ...], int]]:
    """Best-fit decreasing on a histogram: equal bins are handled together."""
    room: dict[int, list[list]] = {}
    spaces = np.zeros(size + 1, bool)

    def put(parts: tuple, n: int) -> None:
        s = size - sum(parts)
        room.setdefault(s, []).append([parts, n])
        spaces[s] = True

    for v in range(size, 0, -1):
        c = int(left[v])
        while c:
            fits = np.flatnonzero(spaces[v:])
            if len(fits):
                s = v + int(fits[0])
                parts, n = room[s].pop()
                if not room[s]:
                    spaces[s] = False
                k = min(c, n)
                if n > k:
                    put(parts, n - k)
                put((*parts, v), k)
                c -= k
            else:
                each = size // v
                if c >= each:
                    put((v,) * each, c // each)
                    c %= each
                else:
                    put((v,) * c, 1)
                    c = 0
    return [(parts, n) for group in room.values() for parts, n in group]


def plan(hist: np.ndarray, size: int = SIZE) -> list[tuple[tuple[int, ...], int]]:
    """Patterns with repeat counts that hold each length exactly as often as the histogram says."""
    hist = hist.astype(np.int64)
    full = [((size,), int(hist[size]))] if hist[size] else []
    rest = hist.copy()
    rest[size] = 0
    p = patterns(np.flatnonzero(rest), size)
    x = fit_counts(p, rest) if len(p) else np.zeros(0)
    best = None
    for share in SHARES:
        for start in STARTS:
            chosen, left = round_counts(p, x, rest, share, start)
            made = [*full, *chosen, *best_fit(left, size)]
            if best is None or sum(n for _, n in made) < sum(n for _, n in best):
                best = made
    return best


def slots(chosen: list[tuple[tuple[int, ...], int]]) -> dict[str, np.ndarray]:
    """Rank ranges: pieces of `length` with ranks from `rank` on go to sequence `seq` + (their rank - rank) at `offset`."""
    seq, used, rows = 0, {}, []
    for parts, n in chosen:
        at = 0
        for v in parts:
            r = used.get(v, 0)
            rows.append((v, r, seq, at))
            used[v] = r + n
            at += v
        seq += n
    a = np.array(sorted(rows), np.int64).reshape(-1, 4)
    return {"length": a[:, 0], "rank": a[:, 1], "seq": a[:, 2], "offset": a[:, 3]}


def _assign(s: dict[str, np.ndarray]):
    key = s["length"] * (1 << 50) + s["rank"]

    def run(batches):
        import pyarrow as pa

        for b in batches:
            length, rank = b.column("length").to_numpy(), b.column("grank").to_numpy()
            i = np.searchsorted(key, length * (1 << 50) + rank, "right") - 1
            seq, off = s["seq"][i] + rank - s["rank"][i], s["offset"][i]
            names = [n for n in b.schema.names if n != "grank"]
            yield pa.RecordBatch.from_arrays([*(b.column(n) for n in names), pa.array(seq), pa.array(off)], names=[*names, "sequence_id", "offset"])

    return run


def pack(df: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", size: int = SIZE, end_id: int = END_ID, with_ids: bool = False) -> DataFrame:
    """One row per piece: id, piece, start, length, ids_crc32, sequence_id, offset (and ids, if asked for)."""
    kind = df.schema[id_col].dataType.simpleString()
    schema = f"id {kind}, piece int, start long, length long, ids_crc32 long, pid int, rank long" + (", ids array<int>" if with_ids else "")
    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    pieces = written(rows.mapInArrow(tidy(_pieces(tokenizer_path, size, end_id, with_ids, kind)), schema), "pieces")
    counts = pieces.groupBy("pid", "length").agg(F.count("*").alias("n"))
    before = F.sum("n").over(Window.partitionBy("length").orderBy("pid").rowsBetween(Window.unboundedPreceding, -1))
    counts = written(counts.select("pid", "length", "n", F.coalesce(before, F.lit(0)).alias("base")), "counts")
    hist = np.zeros(size + 1, np.int64)
    for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect():  # at most `size` rows
        hist[r["length"]] = r["n"]
    ranked = pieces.join(counts.select("pid", "length", "base"), ["pid", "length"]).withColumn("grank", F.col("base") + F.col("rank"))
    cols = ["id", "piece", "start", "length", "ids_crc32", *(["ids"] if with_ids else [])]
    out = ranked.select(*cols, "grank").mapInArrow(tidy(_assign(slots(plan(hist, size)))), f"id {kind}, piece int, start long, length long, ids_crc32 long" + (", ids array<int>" if with_ids else "") + ", sequence_id long, offset long")
    return out.withColumnRenamed("id", id_col)


def sequences(packed: DataFrame) -> DataFrame:
    """Packed sequences with their ids, from pack(..., with_ids=True): sequence_id, input_ids, lengths."""
    parts = packed.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "length", "ids"))).alias("p"))
    return parts.select("sequence_id", F.flatten("p.ids").alias("input_ids"), F.col("p.length").alias("lengths"))


def default_tokenizer() -> str:
    import public_tokenizers

    return str(public_tokenizers.path("byte_bpe_50k.json"))


def op5_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    """All documents in sequences of at most 1024 tokens."""
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"), default_tokenizer())
