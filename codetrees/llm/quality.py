"""Quality classification by attention-based multiple-instance learning.

A document is a bag of passages of 64 words. Every passage of the whole text is encoded as a vector: shares of byte
kinds, word-length and repetition figures, and hashed shares of short words. A gated attention layer (tanh branch times
sigmoid branch) weighs the encoded passages; the weighted mean gives the document's score. All weights are learnt from
document labels alone, by Adam in numpy, on a bounded sample of labelled rows.

Edge rules: null, empty and blank texts are a bag without passages and get the model's score for an empty bag; texts of
any length are encoded in bounded blocks; without any usable label every score is 0.5; repeated rows get equal scores;
labels that are null are ignored, and of several labels of one id the largest counts; an empty table gives an empty
result; extra columns are ignored or, in keep_quality(), passed through.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codetrees.llm.common import crc32_mod, small_batches, tidy
from codetrees.llm.textbytes import byte_columns, word_hashes

PASSAGE = 64  # words
HASHED = 24
KINDS = 11
FEATURES = KINDS + 7 + HASHED
BLOCK = 1 << 18


def _kinds() -> np.ndarray:
    """Byte kinds: 0 other symbol, 1 lower, 2 upper, 3 digit, 4 space, 5 line end, 6 multi-byte, 7 . and ,  8 ! and ?
    9 bars, braces and brackets, 10 quotes, hyphens, colons."""
    t = np.zeros(256, np.uint8)
    t[97:123], t[65:91], t[48:58], t[128:] = 1, 2, 3, 6
    for k, chars in ((4, b" \t\x0b\x0c"), (5, b"\n\r"), (7, b".,"), (8, b"!?"), (9, b"|{}[]<>"), (10, b"'\"-:;()/")):
        t[list(chars)] = k
    return t


KIND = _kinds()


def encode_passages(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Vectors of all passages of the documents, and the document of each."""
    vectors, docs = [], []
    n, i = len(off) - 1, 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(off, off[i] + BLOCK, "right")) - 1)
        v, d = _encode(data[off[i] : off[j]], off[i : j + 1] - off[i])
        vectors.append(v)
        docs.append(d + i)
        i = j
    if not vectors:
        return np.zeros((0, FEATURES), np.float32), np.zeros(0, np.int64)
    return np.concatenate(vectors), np.concatenate(docs)


def _encode(b: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    spaced = np.insert(b, off[1:-1], 32)  # words never cross documents
    starts = off[:-1] + np.arange(len(off) - 1)
    hashes, at = word_hashes(spaced, lower=False)
    if not len(at):
        return np.zeros((0, FEATURES), np.float32), np.zeros(0, np.int64)
    doc = np.searchsorted(starts, at, "right") - 1
    first = np.searchsorted(doc, np.arange(len(starts)))  # each document's first word
    nth = np.arange(len(at)) - first[doc]
    new = (nth % PASSAGE) == 0
    passage = np.cumsum(new) - 1
    p = int(passage[-1]) + 1
    begin = at[new]
    stop = np.append(starts[1:] - 1, len(spaced))  # where each document ends
    follow = np.append(begin[1:], len(spaced))
    end = np.minimum(follow, stop[doc[new]])
    words = np.bincount(passage, minlength=p).astype(np.float64)

    where = np.repeat(np.arange(p), follow - begin)
    own = np.arange(begin[0], len(spaced)) < end[where]
    kinds = KIND[spaced[begin[0] :]]
    kind = np.bincount((where * KINDS + kinds)[own], minlength=p * KINDS).reshape(p, KINDS)
    size = np.maximum(end - begin, 1)
    out = np.zeros((p, FEATURES), np.float32)
    out[:, :KINDS] = kind / size[:, None]

    nxt = np.minimum(np.append(at[1:], len(spaced) + 1), stop[doc] + 1)
    length = np.minimum(nxt - at - 1, 40)
    same_doc = np.append(False, doc[1:] == doc[:-1])
    again = np.append(False, hashes[1:] == hashes[:-1]) & same_doc
    order = np.lexsort((hashes, passage))
    fresh = np.ones(len(order), bool)
    fresh[1:] = (hashes[order][1:] != hashes[order][:-1]) | (passage[order][1:] != passage[order][:-1])
    old = np.zeros(len(hashes), bool)  # word pairs seen before in the document
    after = np.zeros(len(hashes), np.uint64)
    after[:-1] = np.where(doc[1:] == doc[:-1], hashes[1:], np.uint64(0))
    pair = hashes * np.uint64(31) + after
    seen = np.lexsort((np.arange(len(pair)), pair, doc))
    old[seen[1:]] = (pair[seen][1:] == pair[seen][:-1]) & (doc[seen][1:] == doc[seen][:-1])
    extra = (
        np.bincount(passage, length, p) / words / 10,
        np.bincount(passage, length**2, p) / words / 100,
        np.bincount(passage, again, p) / words,
        np.bincount(passage[order], fresh, p) / words,
        np.bincount(passage, old, p) / words,
        np.bincount(passage, length <= 3, p) / words,
        np.log1p(words) / 5,
    )
    for k, x in enumerate(extra):
        out[:, KINDS + k] = x
    short = np.flatnonzero(length <= 4)
    cell = passage[short] * HASHED + (hashes[short] >> np.uint64(40)).astype(np.int64) % HASHED
    out[:, KINDS + 7 :] = np.bincount(cell, minlength=p * HASHED).reshape(p, HASHED) / words[:, None]
    return out, doc[new]


class Bags:
    """Passage vectors sorted by document, with a slot for every document, empty ones too."""

    def __init__(self, x: np.ndarray, doc: np.ndarray, n: int):
        self.x, self.doc, self.n = x, doc, n

    def sums(self, v: np.ndarray) -> np.ndarray:
        out = np.zeros((self.n, v.shape[1]))
        np.add.at(out, self.doc, v) if len(v) < 64 else self._fast(v, out)
        return out

    def _fast(self, v, out):
        for c in range(v.shape[1]):
            out[:, c] = np.bincount(self.doc, v[:, c], self.n)

    def largest(self, v: np.ndarray) -> np.ndarray:
        out = np.full(self.n, -np.inf)
        np.maximum.at(out, self.doc, v)
        return out


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


class GatedAttention:
    """h = tanh(x W0 + b0); a = softmax over passages of (tanh(h V) * sigmoid(h U)) w; score = sigmoid(sum(a h) c + b)."""

    def __init__(self, features: int = FEATURES, hidden: int = 24, gate: int = 12, seed: int = 11):
        rng = np.random.default_rng(seed)
        s = lambda a, b: rng.normal(0, 1 / np.sqrt(a), (a, b))
        self.p = {"W0": s(features, hidden), "b0": np.zeros(hidden), "V": s(hidden, gate), "U": s(hidden, gate), "w": s(gate, 1), "c": s(hidden, 1), "b": np.zeros(1)}
        self.mean, self.scale = np.zeros(features), np.ones(features)

    def forward(self, bags: Bags):
        p = self.p
        x = (bags.x - self.mean) / self.scale
        h = np.tanh(x @ p["W0"] + p["b0"])
        t, g = np.tanh(h @ p["V"]), _sigmoid(h @ p["U"])
        e = ((t * g) @ p["w"])[:, 0]
        e = np.exp(e - bags.largest(e)[bags.doc])
        a = e / bags.sums(e[:, None])[bags.doc, 0]
        z = bags.sums(a[:, None] * h)
        return x, h, t, g, a, z, _sigmoid(z @ p["c"] + p["b"])[:, 0]

    def gradients(self, bags: Bags, y: np.ndarray, weight: np.ndarray):
        p = self.p
        x, h, t, g, a, z, out = self.forward(bags)
        d = ((out - y) * weight / weight.sum())[:, None]
        grad = {"c": z.T @ d, "b": d.sum(0)}
        dz = d @ p["c"].T
        da = (dz[bags.doc] * h).sum(1)
        mean = bags.sums((a * da)[:, None])[:, 0]
        de = (a * (da - mean[bags.doc]))[:, None]
        grad["w"] = (t * g).T @ de
        dg = de @ p["w"].T
        dt, ds = dg * g * (1 - t**2), dg * t * g * (1 - g)
        grad["V"], grad["U"] = h.T @ dt, h.T @ ds
        dh = a[:, None] * dz[bags.doc] + dt @ p["V"].T + ds @ p["U"].T
        dh *= 1 - h**2
        grad["W0"], grad["b0"] = x.T @ dh, dh.sum(0)
        return grad, out

    def fit(self, x: np.ndarray, doc: np.ndarray, y: np.ndarray, epochs: int = 60, batch: int = 128, rate: float = 0.01, decay: float = 1e-3, seed: int = 5) -> GatedAttention:
        rng = np.random.default_rng(seed)
        if len(x):
            self.mean, self.scale = x.mean(0), x.std(0) + 1e-3
        n = len(y)
        lo, hi = np.searchsorted(doc, np.arange(n)), np.searchsorted(doc, np.arange(n), "right")
        m = {k: np.zeros_like(v) for k, v in self.p.items()}
        s = {k: np.zeros_like(v) for k, v in self.p.items()}
        weight = np.where(y == 1, 0.5 / max(y.mean(), 1e-6), 0.5 / max(1 - y.mean(), 1e-6))
        step = 0
        for epoch in range(epochs):
            lr = rate * (1 - epoch / epochs) + 1e-4
            for some in np.array_split(rng.permutation(n), max(1, -(-n // batch))):
                some.sort()
                rows = np.concatenate([np.arange(lo[k], hi[k]) for k in some])
                local = np.repeat(np.arange(len(some)), hi[some] - lo[some])
                grad, _ = self.gradients(Bags(x[rows], local, len(some)), y[some], weight[some])
                step += 1
                for k, g in grad.items():
                    g = g + decay * self.p[k] * (k not in ("b", "b0"))
                    m[k] = 0.9 * m[k] + 0.1 * g
                    s[k] = 0.999 * s[k] + 0.001 * g * g
                    self.p[k] = self.p[k] - lr * (m[k] / (1 - 0.9**step)) / (np.sqrt(s[k] / (1 - 0.999**step)) + 1e-8)
        # The prior of the sample instead of the balanced one: scores are probabilities of label 1.
        self.p["b"] = self.p["b"] + np.log(max(y.mean(), 1e-6) / max(1 - y.mean(), 1e-6)) * (0 < y.mean() < 1)
        return self

    def score(self, data: np.ndarray, off: np.ndarray) -> np.ndarray:
        x, doc = encode_passages(data, off)
        return self.forward(Bags(x, doc, len(off) - 1))[-1]


def _passages(batches):
    import pyarrow as pa

    for b in batches:
        data, off = byte_columns(b.column("text"))
        x, doc = encode_passages(data, off)
        lo = np.searchsorted(doc, np.arange(b.num_rows + 1))
        yield pa.RecordBatch.from_arrays([b.column("id"), b.column("label"), pa.array([x[lo[i] : lo[i + 1]].astype("<f4").tobytes() for i in range(b.num_rows)], pa.binary())], names=["id", "label", "x"])


def train_quality_model(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", max_rows: int = 4000, **options) -> GatedAttention | None:
    """Fit on at most max_rows distinct labelled texts (the documented bound): of the labelled ids with the least hashes,
    the first texts by hash. Repeated rows count once, as often as they may come."""
    small_batches(docs.sparkSession)
    known = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.max(F.col(label_col).cast("int")).alias("label"))
    some = known.orderBy(F.xxhash64(F.col("id").cast("string")), "id").limit(max_rows)
    texts = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text")).join(F.broadcast(some), "id").withColumn("h", F.xxhash64("text"))
    first = texts.select("id", "h").distinct().orderBy(F.xxhash64(F.col("id").cast("string")), "id", "h").limit(max_rows)
    rows = texts.join(F.broadcast(first), ["id", "h"], "left_semi").groupBy("id", "h").agg(F.first("label").alias("label"), F.min("text").alias("text"))
    kind = rows.schema["id"].dataType.simpleString()
    got = rows.select("id", "label", "text").mapInArrow(tidy(_passages), f"id {kind}, label int, x binary").collect()
    got = sorted(got, key=lambda r: (r["id"], len(r["x"]), r["x"][:64]))
    if not got:
        return None
    xs = [np.frombuffer(r["x"], "<f4").reshape(-1, FEATURES) for r in got]
    doc = np.repeat(np.arange(len(xs)), [len(x) for x in xs])
    return GatedAttention().fit(np.concatenate(xs).astype(np.float64), doc, np.array([r["label"] > 0 for r in got], float), **options)


def _scored(model: GatedAttention | None, threshold: float, text_col: str, select: bool):
    def run(batches):
        import pyarrow as pa

        for b in batches:
            for at in range(0, b.num_rows, 1000):
                part = b.slice(at, 1000)
                score = model.score(*byte_columns(part.column(text_col))) if model else np.full(part.num_rows, 0.5)
                if select:
                    yield part.filter(pa.array(score >= threshold))
                else:
                    yield pa.RecordBatch.from_arrays([part.column("id"), pa.array(score), pa.array((score >= threshold).astype(np.int32))], names=["id", "score", "predicted"])

    return run


def score_quality(df: DataFrame, model: GatedAttention | None, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.3) -> DataFrame:
    """One row per document: id, score (0 to 1), predicted (1 if score >= threshold)."""
    small_batches(df.sparkSession)
    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(tidy(_scored(model, threshold, "text", False)), f"id {df.schema[id_col].dataType.simpleString()}, score double, predicted int").withColumnRenamed("id", id_col)


def keep_quality(df: DataFrame, model: GatedAttention | None, text_col: str = "text", threshold: float = 0.3) -> DataFrame:
    """The rows of df, all columns, whose score reaches the threshold."""
    small_batches(df.sparkSession)
    return df.mapInArrow(tidy(_scored(model, threshold, text_col, True)), df.schema)


def held_out(id_col: str = "doc_id"):
    """Rows never learnt from: crc32 of the id as text modulo 5 is 0."""
    return F.coalesce(crc32_mod(F.col(id_col), 5), F.lit(1)) == 0


def op2_quality(spark, sf_dir: str) -> DataFrame:
    """All documents, learnt from labels.quality of rows that are not held out."""
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    model = train_quality_model(docs, labels.where(~held_out()))
    return score_quality(docs, model).withColumn("held_out", held_out())
