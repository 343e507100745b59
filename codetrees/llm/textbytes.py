"""Words and word shingles of UTF-8 texts as numpy arrays, whole texts at a time, in bounded pieces."""

from __future__ import annotations

import numpy as np

from codetrees.llm.common import mix64, worker_cache

PIECE = 1 << 20
PRIME = 0x9E3779B97F4A7C15  # odd, so it has an inverse modulo 2**64


def _tables(n: int):
    c = worker_cache()
    if c.get("pow_n", 0) < n:
        n = max(n, PIECE + 4096)
        inverse = pow(PRIME, -1, 1 << 64)
        ones = np.ones(n + 1, np.uint64)
        for name, base in (("pow", PRIME), ("inv", inverse)):
            p = ones.copy()
            p[1:] = np.uint64(base)
            c[name] = np.multiply.accumulate(p)
        c["pow_n"] = n
    if "lower" not in c:
        lower = np.arange(256, dtype=np.uint8)
        lower[65:91] += 32
        space = np.zeros(256, np.uint8)
        space[[0x20, *range(0x09, 0x0E)]] = 1
        c["lower"], c["space"] = lower, space
    return c


def word_hashes(data: np.ndarray, lower: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hash and start of each word ([^\\x20\\x09-\\x0D]+) of a byte array, A-Z lower-cased first."""
    c = _tables(PIECE)
    hashes, starts, at, n = [], [], 0, len(data)
    while at < n:
        end = min(n, at + PIECE)
        while end < n:  # cut only at white space
            back = np.flatnonzero(c["space"][data[max(at, end - 65536) : end]])
            if len(back):
                end = max(at, end - 65536) + int(back[-1]) + 1
                break
            end = min(n, end + PIECE)
        piece = data[at:end]
        h, s = _piece(piece, lower)
        hashes.append(h)
        starts.append(s + at)
        at = end
    if not hashes:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return np.concatenate(hashes), np.concatenate(starts)


def _piece(b: np.ndarray, lower: bool):
    c = _tables(len(b) + 1)
    space = c["space"][b]
    edge = np.flatnonzero(np.diff(space, prepend=1, append=1))
    s, e = edge[::2], edge[1::2]
    low = c["lower"][b] if lower else b
    total = np.zeros(len(b) + 1, np.uint64)
    np.cumsum((low.astype(np.uint64) + np.uint64(1)) * c["pow"][: len(b)], out=total[1:])
    return mix64((total[e] - total[s]) * c["inv"][s]), s


def shingles(data: np.ndarray, k: int = 5) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's k-word shingles; with fewer words the whole sequence is one."""
    w, _ = word_hashes(data)
    return shingle_set(w, k)


def shingle_set(w: np.ndarray, k: int) -> np.ndarray:
    if len(w) == 0:
        return w
    width = min(k, len(w))
    n = len(w) - width + 1
    h = np.zeros(n, np.uint64)
    for j in range(width):
        h = mix64(h * np.uint64(PRIME) + w[j : j + n])
    if len(w) < k:
        h = mix64(h + np.uint64(len(w)))
    h.sort()
    return h[np.concatenate([[True], h[1:] != h[:-1]])]


def byte_columns(array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow string/binary array, nulls as empty; no copy of the values."""
    import pyarrow as pa

    if isinstance(array, pa.ChunkedArray):
        array = array.combine_chunks()
    if array.null_count:
        array = array.fill_null("" if pa.types.is_string(array.type) or pa.types.is_large_string(array.type) else b"")
    wide = pa.types.is_large_string(array.type) or pa.types.is_large_binary(array.type)
    bufs = array.buffers()
    off = np.frombuffer(bufs[1], np.int64 if wide else np.int32)[array.offset : array.offset + len(array) + 1].astype(np.int64) if len(array) else np.zeros(1, np.int64)
    data = np.frombuffer(bufs[2], np.uint8) if bufs[2] is not None and bufs[2].size else np.zeros(0, np.uint8)
    return data, off
