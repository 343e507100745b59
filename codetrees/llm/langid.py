"""Language identification: averaged hashed subword embeddings under a linear softmax, trained by SGD in numpy.

A text's subwords are its byte n-grams (2 to 4) inside words, with a word-boundary mark, hashed to a table of rows. The
mean of their rows goes through a linear softmax. As the model is linear after the embedding, scoring folds both into
one table of per-subword class scores, and a text's logits are the mean of its subwords' scores over the whole text.
A temperature fitted on a part of the sample kept from training calibrates the probabilities; the rejection threshold is
the calibrated probability below which held-back texts fell short of the wanted precision.

Edge rules: texts that are null or have no letter are `und` with score 0; a text with letters but no subword falls back
to the bias alone; without any usable training row every text is `und`; repeated rows give repeated predictions; an
empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codetrees.llm.common import crc32_mod, mix64, small_batches, tidy
from codetrees.llm.textbytes import byte_columns

BUCKETS = 1 << 15
BLOCK = 1 << 20
GRAMS = (2, 3, 4)


def _fold() -> np.ndarray:
    """Byte classes: letters lower-cased, bytes of multi-byte characters as they are, all else a boundary (0)."""
    t = np.zeros(256, np.uint8)
    t[97:123] = np.arange(97, 123)
    t[65:91] = np.arange(97, 123)
    t[128:] = np.arange(128, 256)
    return t


FOLD = _fold()


def subwords(b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bucket, position) of each subword of folded bytes; boundaries only at a subword's ends."""
    b = np.concatenate([[0], b, [0]]).astype(np.uint64)
    edge = b == 0
    out, where = [], []
    for n in GRAMS:
        m = len(b) - n + 1
        if m <= 0:
            continue
        h = np.full(m, n, np.uint64)
        inner = np.zeros(m, bool)
        for j in range(n):
            h = h * np.uint64(0x100000001B3) + b[j : j + m]
            if 0 < j < n - 1:
                inner |= edge[j : j + m]
        if n == 2:
            inner = edge[:m] & edge[1:]
        at = np.flatnonzero(~inner)
        out.append((mix64(h[at]) >> np.uint64(49)).astype(np.int32))
        where.append(np.minimum(np.maximum(at - 1, 0), max(0, len(b) - 3)))
    return np.concatenate(out), np.concatenate(where)


def _pieces(f: np.ndarray):
    """Cut folded bytes at boundaries into pieces of about BLOCK bytes; a boundary at a cut belongs to both sides."""
    lo = 0
    while lo < len(f):
        hi = min(len(f), lo + BLOCK)
        while hi < len(f):
            back = np.flatnonzero(f[lo + 1 : hi] == 0)
            if len(back):
                hi = lo + 2 + int(back[-1])
                break
            hi = min(len(f), hi + BLOCK)
        yield lo, f[lo:hi]
        if hi >= len(f):
            return
        lo = hi - 1


def document_sums(data: np.ndarray, off: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per document: sum of table rows over its subwords, number of subwords, number of ASCII letters."""
    n, k = len(off) - 1, table.shape[1]
    sums, counts, letters = np.zeros((n, k)), np.zeros(n), np.zeros(n)
    i = 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(off, off[i] + 4 * BLOCK, "right")) - 1)
        starts = off[i:j] - off[i]
        f = np.insert(FOLD[data[off[i] : off[j]]], starts, 0)  # each document begins with a boundary
        starts = starts + np.arange(j - i)
        for lo, piece in _pieces(f):
            b, at = subwords(piece)
            doc = np.searchsorted(starts, at + lo, "right") - 1 + i
            for c in range(k):
                sums[:, c] += np.bincount(doc, table[b, c], n)
            counts += np.bincount(doc, minlength=n)
            letter = np.flatnonzero((piece >= 97) & (piece < 123))
            letters += np.bincount(np.searchsorted(starts, letter + lo, "right") - 1 + i, minlength=n)
        i = j
    return sums, counts, letters


def _features(batches):
    import pyarrow as pa

    for b in batches:
        data, off = byte_columns(b.column("text"))
        rows = []
        for i in range(b.num_rows):
            x, _ = subwords(FOLD[data[off[i] : off[i + 1]]])
            u, c = np.unique(x, return_counts=True)
            rows.append((u.astype("<i4").tobytes(), c.astype("<f4").tobytes()))
        yield pa.RecordBatch.from_arrays([b.column("lang"), pa.array([r[0] for r in rows], pa.binary()), pa.array([r[1] for r in rows], pa.binary())], names=["lang", "idx", "cnt"])


class Model:
    """langs, per-subword class scores (BUCKETS x classes), bias, temperature, rejection threshold."""

    def __init__(self, langs, table, bias, temperature, reject_below):
        self.langs, self.table, self.bias, self.temperature, self.reject_below = langs, table, bias, temperature, reject_below


def _probabilities(logits: np.ndarray) -> np.ndarray:
    e = np.exp(logits - logits.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


def fit(rows: list[tuple[str, np.ndarray, np.ndarray]], dim: int = 16, epochs: int = 20, rate: float = 1.0, seed: int = 7, precision: float = 0.98) -> Model:
    """SGD over (language, subword buckets, counts); one row in five is kept for calibration."""
    langs = sorted({r[0] for r in rows})
    y = np.array([langs.index(r[0]) for r in rows])
    rng = np.random.default_rng(seed)
    emb = rng.uniform(-1 / dim, 1 / dim, (BUCKETS, dim)).astype(np.float32)
    w, bias = np.zeros((len(langs), dim), np.float32), np.zeros(len(langs), np.float32)
    bags = [(i, (c / max(c.sum(), 1)).astype(np.float32)) for _, i, c in rows]
    held = np.arange(len(rows)) % 5 == 4
    train = np.flatnonzero(~held) if (~held).any() else np.arange(len(rows))
    steps, done = epochs * len(train), 0
    for _ in range(epochs):
        for k in rng.permutation(train):
            i, f = bags[k]
            lr = rate * (1 - done / steps)
            done += 1
            if not len(i):
                continue
            z = f @ emb[i]
            p = w @ z + bias
            p = np.exp(p - p.max())
            p /= p.sum()
            p[y[k]] -= 1
            back = w.T @ p
            w -= lr * np.outer(p, z)
            bias -= lr * 0.01 * p
            emb[i] -= (lr * 10) * np.outer(f, back)  # means of many rows: each row's share of the step is small
    table = emb @ w.T
    test = np.flatnonzero(held) if held.sum() >= 20 else np.arange(len(rows))
    logits = np.stack([(bags[k][1] @ table[bags[k][0]] if len(bags[k][0]) else np.zeros(len(langs))) + bias for k in test])
    grid = np.exp(np.linspace(-6, 3, 91))
    wanted = np.full((len(test), len(langs)), 0.01 / len(langs))  # smoothed labels keep the temperature finite
    wanted[np.arange(len(test)), y[test]] += 0.99
    loss = [-(wanted * np.log(_probabilities(logits / t) + 1e-12)).sum(1).mean() for t in grid]
    t = float(grid[int(np.argmin(loss))])
    p = _probabilities(logits / t)
    order = np.argsort(p.max(1))
    right = (p.argmax(1) == y[test])[order]
    share = right[::-1].cumsum()[::-1] / np.arange(len(right), 0, -1)  # precision when all below are rejected
    ok = np.flatnonzero(share >= precision)
    reject = float(p.max(1)[order[ok[0]]]) if len(ok) else 1.0
    return Model(langs, table.astype(np.float64), bias.astype(np.float64), t, reject)


def train_language_model(df: DataFrame, text_col: str = "text", lang_col: str = "lang", order_col: str = "doc_id", max_rows: int = 2500, **options) -> Model | None:
    """Fit on at most max_rows distinct labelled texts (the documented bound), taken in hash order of order_col, whole
    texts. Repeated rows count once, as often as they may come."""
    small_batches(df.sparkSession)
    known = df.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(order_col).alias("o"), F.col(lang_col).cast("string").alias("lang"), F.col(text_col).cast("string").alias("text"))
    known = known.withColumn("k", F.coalesce(F.col("o").cast("string"), F.lit(""))).withColumn("h", F.xxhash64("text"))
    ids = known.select("k").distinct().orderBy(F.xxhash64("k"), "k").limit(max_rows)
    known = known.join(F.broadcast(ids), "k", "left_semi")
    first = known.select("k", "lang", "h").distinct().orderBy(F.xxhash64("k"), "k", "lang", "h").limit(max_rows)
    some = known.join(F.broadcast(first), ["k", "lang", "h"], "left_semi").groupBy("k", "lang", "h").agg(F.min("text").alias("text"))
    got = some.select("lang", "text").mapInArrow(tidy(_features), "lang string, idx binary, cnt binary").collect()
    data = sorted(((r["lang"], np.frombuffer(r["idx"], "<i4"), np.frombuffer(r["cnt"], "<f4")) for r in got), key=lambda r: (r[0], len(r[1]), r[1].tobytes()[:64]))
    rng = np.random.default_rng(3)
    data = [data[i] for i in rng.permutation(len(data))]
    return fit(data, **options) if data else None


def _predict(model: Model | None, reject: bool):
    def run(batches):
        import pyarrow as pa

        for b in batches:
            for at in range(0, b.num_rows, 2000):
                x = b.slice(at, 2000)
                n = x.num_rows
                data, off = byte_columns(x.column("text"))
                table = model.table if model else np.zeros((BUCKETS, 1))
                sums, counts, letters = document_sums(data, off, table)
                texts = None
                has = letters > 0
                for i in np.flatnonzero(~has & (np.diff(off) > 0)):
                    texts = texts or x.column("text")
                    has[i] = any(c.isalpha() for c in texts[int(i)].as_py())
                if model:
                    p = _probabilities((sums / np.maximum(counts, 1)[:, None] + model.bias) / model.temperature)
                    best, score = p.argmax(1), p.max(1)
                    said = [model.langs[c] for c in best]
                else:
                    score, said = np.zeros(n), ["und"] * n
                unsure = score < (model.reject_below if model else 1.0)
                pred = ["und" if not h or (reject and u) else s for h, s, u in zip(has, said, unsure, strict=True)]
                yield pa.RecordBatch.from_arrays([x.column("id"), pa.array(pred), pa.array(np.where(has, score, 0.0)), pa.array(has & ~unsure)], names=["id", "lang_pred", "score", "sure"])

    return run


def identify(df: DataFrame, model: Model | None, id_col: str = "doc_id", text_col: str = "text", reject: bool = True) -> DataFrame:
    """One row per document: id, lang_pred, score (calibrated), sure (score at or over the rejection threshold).
    reject: say `und` where not sure."""
    small_batches(df.sparkSession)
    kind = df.schema[id_col].dataType.simpleString()
    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(tidy(_predict(model, reject)), f"id {kind}, lang_pred string, score double, sure boolean").withColumnRenamed("id", id_col)


def op6_language_id(spark, sf_dir: str) -> DataFrame:
    """All documents; rows whose crc32(doc_id) mod 4 is 2 are never learnt from."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = F.coalesce(crc32_mod(F.col("doc_id"), 4), F.lit(0)) == 2
    model = train_language_model(docs.where(~out))
    return identify(docs, model, reject=False).withColumn("held_out", out)
