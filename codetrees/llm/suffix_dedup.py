"""Removal of long repeated substrings by column-wise multi-document suffix sorting.

Which bytes of a text lie in a string of `length` bytes that also starts anywhere else is a question about suffixes: a
position is repeated when the suffix there shares `length` bytes with a neighbour in suffix order. The order is built
column by column: each round inserts one symbol of every string of a collection, in front of what it had, and updates
the collection's transform (the symbols of the next round in the present order) and the common prefixes of neighbours.

Inserting into one collection of whole texts takes as many rounds as the longest text has bytes, each over all data. So
the collections are made small and short first, without losing a match. Every window of `length` bytes is filed under
its least hashed 32-byte substring (leftmost if tied), which depends on its bytes alone; neighbouring windows with the
same occurrence of it form a segment. Equal windows thus lie in segments of one group, at the same distance from the
anchor. Segments whose whole content occurs twice are repeated throughout; only groups with different contents need
suffix sorting, one copy of each content. Aligned at their anchors, equal windows start in the same column, so a round
only has to order the suffixes that begin in its column, and the rounds are at most 2 * length. Groups of very many
contents, as of a line that many documents hold, are divided once more: windows that start in the same STRIP columns by
the bytes that all of them hold, which are length - STRIP + 1. Should more than COLLECTION contents share even these, their
windows (STRIP each at most) are compared by 128-bit digests, which need 360 bytes a content.

What the method's external files are for, bounded memory and sequential passes, is left to Spark: segments and contents
stream through shuffle files, each collection is a bounded block of groups, and its transform lives in memory.

Edge rules: null and empty texts have no bytes; texts shorter than `length` are kept; repeated rows repeat each other
and lose every byte if long enough; overlaps within a document count; documents longer than a block are cut into pieces
that overlap by length - 1 bytes; null ids are kept; an empty table gives an empty result; extra columns are ignored.
Whole segments are compared by 128-bit hashes, windows of differing segments by their bytes.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codetrees.llm.common import RID, dropped, keyed, mix64, small_batches, tidy, worker_cache, written
from codetrees.llm.textbytes import byte_columns

ANCHOR = 32
PIECE_BITS = 20
PIECE = 1 << PIECE_BITS
SPLIT = 5000  # contents of a group from which on it is divided
FILED = 400_000  # segments compared within a task before they are dealt out
STRIP = 10  # columns of a divided group
COLLECTION = 20_000  # strings sorted together
SEGMENT = np.dtype([("mh", "<u8"), ("c1", "<u8"), ("c2", "<u8"), ("rid", "<i8"), ("start", "<i8"), ("anchor", "<i4"), ("nwin", "<i4"), ("seen", "u1")])


def _hash_tables(which: int):
    cache = worker_cache()
    name = ("bytes", which)
    if name not in cache:
        base = (0x9E3779B97F4A7C15, 0xD1342543DE82EF95)[which]
        value = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(base))
        up, down = np.full(PIECE + 2, np.uint64(base)), np.full(PIECE + 2, np.uint64(pow(base, -1, 1 << 64)))
        up[0] = down[0] = 1
        cache[name] = value, np.multiply.accumulate(up), np.multiply.accumulate(down)
    return cache[name]


def _prefix_sums(b: np.ndarray, table) -> np.ndarray:
    out = np.zeros(len(b) + 1, np.uint64)
    np.cumsum(table[0][b] * table[1][: len(b)], out=out[1:])
    return out


def segments(b: np.ndarray, off: np.ndarray, length: int) -> np.ndarray:
    """Segments of the documents b[off[i]:off[i+1]] (at most PIECE bytes in all); rid is the document's place."""
    n, k = len(b), ANCHOR if length > ANCHOR else max(1, length // 2)
    width = length - k + 1
    if n < length:
        return np.zeros(0, SEGMENT)
    one, two = _hash_tables(0), _hash_tables(1)
    p = _prefix_sums(b, one)
    h = mix64((p[k:] - p[:-k]) * one[2][: n - k + 1])
    low = np.uint64(PIECE - 1)
    v = (h & ~low) | np.arange(len(h), dtype=np.uint64)  # ties go to the left
    m = len(v)
    pad = np.full(-(-m // width) * width, np.iinfo(np.uint64).max, np.uint64)
    pad[:m] = v
    pad = pad.reshape(-1, width)
    ahead = np.minimum.accumulate(pad, 1).ravel()
    back = np.minimum.accumulate(pad[:, ::-1], 1)[:, ::-1].ravel()
    least = np.minimum(back[: m - width + 1], ahead[width - 1 : m])
    at = np.arange(len(least))
    doc = np.searchsorted(off, at, "right") - 1
    inside = at + length <= off[doc + 1]
    at, doc, anchor = at[inside], doc[inside], (least[inside] & low).astype(np.int64)
    if not len(at):
        return np.zeros(0, SEGMENT)
    cut = np.flatnonzero(np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (doc[1:] != doc[:-1])]))
    out = np.zeros(len(cut), SEGMENT)
    start, nwin = at[cut], np.diff(np.append(cut, len(at)))
    end = start + nwin - 1 + length
    q = _prefix_sums(b, two)
    out["mh"] = h[anchor[cut]]
    out["c1"] = mix64((p[end] - p[start]) * one[2][start] + nwin.astype(np.uint64))
    out["c2"] = mix64((q[end] - q[start]) * two[2][start] + (anchor[cut] - start).astype(np.uint64))
    out["rid"], out["start"], out["anchor"], out["nwin"] = doc[cut], start - off[doc[cut]], anchor[cut] - start, nwin
    return out


def all_segments(data: np.ndarray, off: np.ndarray, rids: np.ndarray, length: int) -> np.ndarray:
    """Segments of any documents, block by block; a document longer than a block in overlapping pieces."""
    found, i, n = [], 0, len(rids)
    while i < n:
        size = off[i + 1] - off[i]
        if size >= PIECE:
            step = PIECE - length
            for lo in range(int(off[i]), int(off[i + 1]) - length + 1, step):
                b = data[lo : min(int(off[i + 1]), lo + step + length - 1)]
                s = segments(b, np.array([0, len(b)]), length)
                s["start"] += lo - off[i]
                s["rid"] = rids[i]
                found.append(s)
            i += 1
            continue
        j = int(np.searchsorted(off, off[i] + PIECE - 1, "right")) - 1
        j = max(j, i + 1)
        s = segments(data[off[i] : off[j]], off[i : j + 1] - off[i], length)
        s["rid"] = rids[i:j][s["rid"]]
        found.append(s)
        i = j
    return np.concatenate(found) if found else np.zeros(0, SEGMENT)


def classify(s: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sort segments; which are repeated as a whole, which are the first of their content, and how many contents their
    group has: (sorted segments, repeated, first, contents)."""
    s = s[np.lexsort((s["c2"], s["c1"], s["mh"]))]
    if not len(s):
        return s, np.zeros(0, bool), np.zeros(0, bool), np.zeros(0, np.int64)
    group = np.concatenate([[True], s["mh"][1:] != s["mh"][:-1]])
    first = group | np.concatenate([[True], (s["c1"][1:] != s["c1"][:-1]) | (s["c2"][1:] != s["c2"][:-1])])
    content, g = np.cumsum(first) - 1, np.cumsum(group) - 1
    times = np.bincount(content, 1 + s["seen"])  # a copy seen elsewhere counts twice
    return s, times[content] > 1, first, np.bincount(g, first)[g].astype(np.int64)


def _spans_by_row(s: np.ndarray):
    """Rows (rid, blob of start and nwin pairs) of repeated segments."""
    s = s[np.argsort(s["rid"], kind="stable")]
    cut = np.concatenate([[0], np.flatnonzero(np.diff(s["rid"])) + 1, [len(s)]]) if len(s) else np.zeros(1, np.int64)
    pairs = np.stack([s["start"], s["nwin"].astype(np.int64)], 1)
    return [int(s["rid"][a]) for a in cut[:-1]], [pairs[a:z].tobytes() for a, z in zip(cut[:-1], cut[1:], strict=True)]


def _file(length: int, buckets: int):
    """Segments of some batches dealt to buckets by group. Copies among them are known to be repeated: their spans go
    along as such, and one of them stands for all."""

    def run(batches):
        import pyarrow as pa

        def deal(held):
            s, again, first, _ = classify(np.concatenate(held))
            rids, blobs = _spans_by_row(s[again])
            s["seen"][again] = 1
            s = s[first]
            bucket = (mix64(s["mh"]) % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(bucket, kind="stable")
            s, bucket = s[order], bucket[order]
            cut = np.concatenate([[0], np.flatnonzero(np.diff(bucket)) + 1, [len(s)]]) if len(s) else np.zeros(1, np.int64)
            where = [*(int(bucket[a]) for a in cut[:-1]), *(r % buckets for r in rids)]
            spans = [None] * (len(cut) - 1) + rids
            return pa.RecordBatch.from_arrays([pa.array(where, pa.int32()), pa.array(spans, pa.int64()), pa.array([*(s[a:z].tobytes() for a, z in zip(cut[:-1], cut[1:], strict=True)), *blobs], pa.binary())], names=["bucket", "rid", "blob"])

        held = []
        for b in batches:
            data, off = byte_columns(b.column("text"))
            held.append(all_segments(data, off, b.column(RID).to_numpy(), length))
            if sum(map(len, held)) > FILED:
                yield deal(held)
                held = []
        if held:
            yield deal(held)

    return run


def _resolve(batches):
    """Per bucket: spans known to be repeated (nwin null), and the contents that need sorting."""
    import pyarrow as pa

    names = ["rid", "blob", "mh", "start", "anchor", "nwin", "contents"]

    def spans(rids, blobs):
        k = len(rids)
        return pa.RecordBatch.from_arrays([pa.array(rids, pa.int64()), pa.array(blobs, pa.binary()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int32()), pa.nulls(k, pa.int32()), pa.nulls(k, pa.int64())], names=names)

    held: dict[int, list] = {}
    for b in batches:
        known = b.column("rid").is_valid().to_pylist()
        rids, blobs = b.column("rid").to_pylist(), b.column("blob").to_pylist()
        if any(known):
            yield spans([r for r, k in zip(rids, known, strict=True) if k], [x for x, k in zip(blobs, known, strict=True) if k])
        for bucket, x, k in zip(b.column("bucket").to_pylist(), blobs, known, strict=True):
            if not k:
                held.setdefault(bucket, []).append(x)
    while held:
        _, blobs = held.popitem()
        s, again, first, contents = classify(np.frombuffer(b"".join(blobs), SEGMENT))
        fresh = again & (s["seen"] == 0)
        rids, out = _spans_by_row(s[fresh])
        if rids:
            yield spans(rids, out)
        need = first & (contents > 1)
        x, c = s[need], contents[need]
        if len(x):
            yield pa.RecordBatch.from_arrays([pa.array(x["rid"].copy()), pa.nulls(len(x), pa.binary()), pa.array(x["mh"].copy().view(np.int64)), pa.array(x["start"].copy()), pa.array(x["anchor"].copy()), pa.array(x["nwin"].copy()), pa.array(c)], names=names)


def _cut_out(length: int):
    """Contents of wanted segments out of their documents, divided where their group has very many."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            data, off = byte_columns(b.column("text"))
            rids, rows = b.column(RID).to_pylist(), []
            for i, want in enumerate(b.column("want").to_pylist()):
                doc = data[off[i] : off[i + 1]]
                for w in want:
                    s, a, n = w["start"], w["anchor"], w["nwin"]
                    text = doc[s : s + n - 1 + length].tobytes()
                    if w["contents"] <= SPLIT:
                        rows.append((w["mh"], rids[i], s, a, text, 0, n))
                        continue
                    # All windows that start in columns [c, c + STRIP) left of the anchor hold bytes c + STRIP - 1 to c + length.
                    for strip in range((a - n + 1) // STRIP, a // STRIP + 1):
                        lo, hi = max(0, a - strip * STRIP - STRIP + 1), min(n, a - strip * STRIP + 1)
                        if lo < hi:
                            part = text[a - strip * STRIP : a - strip * STRIP - STRIP + 1 + length]
                            key = int.from_bytes(hashlib.blake2b(part, digest_size=8, key=b"%d:%d" % (w["mh"], strip)).digest(), "little", signed=True)
                            rows.append((key, rids[i], s + lo, a - lo, text[lo : hi - 1 + length], 0, hi - lo))
            for at in range(0, len(rows), 5000):
                r = rows[at : at + 5000]
                yield pa.RecordBatch.from_arrays([pa.array([x[c] for x in r], t) for c, t in enumerate((pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary(), pa.int32(), pa.int32()))], names=["g", "rid", "start", "anchor", "content", "lo", "hi"])

    return run


def sort_columns(texts: list[bytes], anchors: np.ndarray, group: np.ndarray, length: int):
    """Insert the strings column by column from the right, aligned at their anchors. Yields for every column, from the
    last to the first: (offset of the column's symbol in each string, which strings share >= length bytes from there with
    a neighbour in the order of their group)."""
    n = len(texts)
    sizes = np.array([len(t) for t in texts], np.int64)
    left, right = int(anchors.max()), int((sizes - anchors).max())
    grid = np.full((left + right, n), 256, np.int16)  # 256: no symbol
    flat = np.frombuffer(b"".join(texts), np.uint8)
    at = np.repeat(left - anchors - (np.cumsum(sizes) - sizes), sizes) + np.arange(len(flat))
    grid[at, np.repeat(np.arange(n), sizes)] = flat
    order = np.argsort(group, kind="stable")
    rank = np.cumsum(np.concatenate([[0], np.diff(group[order]) != 0]))
    code = np.zeros(n, np.int64)
    code[order] = rank * 257
    common = np.zeros(n, np.int64)  # common[k]: bytes shared by the k-1st and the kth suffix in order
    for c in range(left + right - 1, -1, -1):
        key = (code + grid[c])[order]
        move = np.argsort(key, kind="stable")
        key, order = key[move], order[move]
        same = np.concatenate([[False], (key[1:] == key[:-1]) & (key[1:] % 257 != 256)])
        k = np.flatnonzero(same)
        new = np.zeros(n, np.int64)
        if len(k):
            a, z = move[k - 1] + 1, move[k] + 1
            ends = np.empty(2 * len(k), np.int64)
            ends[::2], ends[1::2] = a, z
            low = np.minimum.reduceat(np.append(common, 0), ends)[::2]
            new[k] = np.minimum(low + 1, length)
        common = new
        hit = common >= length
        shared = np.zeros(n, bool)
        shared[order] = hit | np.append(hit[1:], False)
        yield c - left + anchors, shared


def _windows_of(rows: list, length: int) -> np.ndarray:
    """Digests of the windows of strings, with the place of each."""
    out = [(hashlib.blake2b(text[o : o + length], digest_size=16).digest(), rid, start + o) for _, rid, start, _, text, lo, hi in rows for o in range(lo, hi)]
    return np.array(out, np.dtype([("d", "S16"), ("rid", "<i8"), ("start", "<i8")]))


def _same_windows(parts: list[np.ndarray]):
    """Spans of windows whose digest occurs twice."""
    import pyarrow as pa

    w = np.concatenate(parts)
    _, which, times = np.unique(w["d"], return_inverse=True, return_counts=True)
    w = w[times[which] > 1]
    s = np.zeros(len(w), SEGMENT)
    s["rid"], s["start"], s["nwin"] = w["rid"], w["start"], 1
    rids, blobs = _spans_by_row(s)
    return pa.RecordBatch.from_arrays([pa.array(rids, pa.int64()), pa.array(blobs, pa.binary())], names=["rid", "blob"])


def _sort(length: int):
    def run(batches):
        import pyarrow as pa

        def spans(rows):
            g, rid, start, anchor, text, lo, hi = (list(x) for x in zip(*rows, strict=True))
            rid, start, lo, hi = (np.array(x, np.int64) for x in (rid, start, lo, hi))
            names = np.unique(np.array(g, np.int64), return_inverse=True)[1]
            begin, found = np.full(len(rows), -1), []
            for offset, shared in sort_columns(text, np.array(anchor, np.int64), names, length):
                on = shared & (offset >= lo) & (offset < hi)
                # Columns run from right to left: a run of windows ends where it is left.
                closed = ~on & (begin >= 0)
                for i in np.flatnonzero(closed):
                    found.append((i, offset[i] + 1, begin[i] - offset[i]))
                begin[closed] = -1
                begin[on & (begin < 0)] = offset[on & (begin < 0)]
            for i in np.flatnonzero(begin >= 0):
                found.append((i, 0, begin[i] + 1))
            s = np.zeros(len(found), SEGMENT)
            if found:
                i, o, k = (np.array(x, np.int64) for x in zip(*found, strict=True))
                s["rid"], s["start"], s["nwin"] = rid[i], start[i] + o, k
            rids, blobs = _spans_by_row(s)
            return pa.RecordBatch.from_arrays([pa.array(rids, pa.int64()), pa.array(blobs, pa.binary())], names=["rid", "blob"])

        held: list = []
        large: list = []  # windows of a group that is too large to be sorted at once
        for b in batches:
            for row in zip(*(b.column(c).to_pylist() for c in ("g", "rid", "start", "anchor", "content", "lo", "hi")), strict=True):
                if held and len(held) >= COLLECTION:
                    name = held[-1][0]
                    if row[0] != name and not large:
                        yield spans(held)
                        held = []
                    elif held[0][0] == name or row[0] == name:
                        before = [r for r in held if r[0] != name]
                        if before:
                            yield spans(before)
                        large.append(_windows_of([r for r in held if r[0] == name], length))
                        held = []
                        if row[0] != name:
                            yield _same_windows(large)
                            large = []
                elif large and row[0] != last:
                    large.append(_windows_of(held, length))
                    yield _same_windows(large)
                    held, large = [], []
                last = row[0]
                held.append(row)
        if large:
            yield _same_windows([*large, _windows_of(held, length)])
        elif held:
            yield spans(held)

    return run


def _cover(blobs: list[bytes], size: int, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of bytes covered by repeated windows: (starts, ends)."""
    pairs = np.frombuffer(b"".join(blobs), np.int64).reshape(-1, 2)
    pairs = pairs[np.argsort(pairs[:, 0], kind="stable")]
    a, z = pairs[:, 0], np.maximum.accumulate(pairs[:, 0] + pairs[:, 1] - 1 + length)
    new = np.concatenate([[True], a[1:] > z[:-1]])
    start = a[new]
    end = np.append(z[np.flatnonzero(new)[1:] - 1], z[-1])
    return start, np.minimum(end, size)


def _strip(length: int, with_text: bool):
    def run(batches):
        import pyarrow as pa

        for b in batches:
            data, off = byte_columns(b.column("text"))
            rows = []
            for i, blobs in enumerate(b.column("spans").to_pylist()):
                doc = data[off[i] : off[i + 1]]
                removed = count = 0
                if blobs:
                    start, end = _cover(blobs, len(doc), length)
                    keep = np.zeros(len(doc) + 1, np.int8)
                    keep[start] += 1
                    keep[end] -= 1
                    count, n = len(start), len(doc)
                    doc = doc[np.cumsum(keep[:-1]) == 0]
                    removed = n - len(doc)
                kept = doc.tobytes()
                rows.append((len(kept) + removed, removed, count, hashlib.sha256(kept).hexdigest(), kept))
            cols = [pa.array([r[c] for r in rows], t) for c, t in enumerate((pa.int64(), pa.int64(), pa.int64(), pa.string()))]
            if with_text:
                cols.append(pa.array([r[4] for r in rows], pa.binary()))
            yield pa.RecordBatch.from_arrays([b.column(RID), b.column("id"), *cols], names=[RID, "id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"][: 2 + len(cols)])

    return run


def repeated_spans(docs: DataFrame, length: int = 200) -> DataFrame:
    """docs: RID, text -> (rid, blob): starts and numbers of repeated windows, as pairs of 64-bit integers."""
    spark = docs.sparkSession
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    filed = docs.mapInArrow(tidy(_file(length, parts)), "bucket int, rid long, blob binary").repartition(parts, "bucket")
    known = written(filed.mapInArrow(tidy(_resolve), "rid long, blob binary, mh long, start long, anchor int, nwin int, contents long"), "segments")
    want = known.where("mh is not null").groupBy(F.col("rid").alias(RID)).agg(F.collect_list(F.struct("mh", "start", "anchor", "nwin", "contents")).alias("want"))
    contents = docs.join(want, RID).select(RID, "text", "want").mapInArrow(tidy(_cut_out(length)), "g long, rid long, start long, anchor int, content binary, lo int, hi int")
    ordered = contents.repartition("g").sortWithinPartitions("g")
    found = written(ordered.mapInArrow(tidy(_sort(length)), "rid long, blob binary"), "sorted")
    return known.where("mh is null").select("rid", "blob").unionByName(found)


def remove_repeats(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = 200, with_text: bool = False) -> DataFrame:
    """One row per input row: RID, id, n_bytes, n_removed, n_spans, kept_sha256 (and kept: the bytes left, if asked for)."""
    docs = keyed(df, id_col, [text_col]).select(RID, F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    spans = repeated_spans(docs.select(RID, "text"), length).groupBy(F.col("rid").alias(RID)).agg(F.collect_list("blob").alias("spans"))
    kind = docs.schema["id"].dataType.simpleString()
    schema = f"{RID} long, id {kind}, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept binary" if with_text else "")
    return docs.join(spans, RID, "left").select(RID, "id", "text", "spans").mapInArrow(tidy(_strip(length, with_text)), schema).withColumnRenamed("id", id_col)


def op8_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    """All documents without bytes of strings of 200 bytes that start twice."""
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop(RID)
