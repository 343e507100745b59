"""Benchmark decontamination with DataFrame functions only.

Benchmark windows (13 consecutive normalised words; a shorter item is one window of its own length) are tested in the scan
of the documents. While they are at most `max_literals`, they are sets inside the scan expression, which Spark keeps as
hash sets: a document position is hit when its outer words and then its window's text are in them. More windows are a
broadcast table of 64-bit hashes, while they are at most BROADCAST (checked by a count): the hashes of a document's
windows are probed in the scan, and the few positions that are left are verified by the windows' texts. Beyond that, the
hashes of all windows, without their texts, are shuffled to the benchmark's.

Edge rules: null text and null items have no words and never match; null item ids are skipped; repeated benchmark rows
count once per item id; repeated documents each get a row; empty tables give empty results (an empty benchmark leaves
all documents clean); extra columns, whatever their names, are ignored or, in decontaminate(), passed through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from codetrees.llm.common import ascii_lower, fresh, written

WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
N = 13
BROADCAST = 2_000_000  # distinct windows whose hashes are broadcast: 16 MB of longs


def words(c: Column) -> Column:
    return F.regexp_extract_all(ascii_lower(F.coalesce(c, F.lit(""))), F.lit(WORD), 0)


def _windows(width: Column, n: Column) -> Column:
    return F.when(n >= width, F.sequence(F.lit(1), n - width + 1)).otherwise(F.array().cast("array<int>"))


def benchmark_windows(benchmark: DataFrame, item_col: str = "item_id", text_col: str = "text", n: int = N) -> DataFrame:
    """Distinct (item, width, win): the items' windows as words joined by a space."""
    items = benchmark.where(F.col(item_col).isNotNull()).select(F.col(item_col).cast("string").alias("item"), words(F.col(text_col)).alias("w")).where("size(w) > 0")
    items = items.withColumn("width", F.least(F.lit(n), F.size("w")))
    at = items.withColumn("i", F.explode(_windows(F.col("width"), F.size("w"))))
    return at.select("item", "width", F.array_join(F.slice("w", F.col("i"), F.col("width")), " ").alias("win")).distinct()


def _in(values) -> str:
    return "(" + ",".join(values) + ")"


def _hits_expr(windows: list[tuple[int, str]], w: str) -> str:
    """SQL for array<struct<i int, width int, win string>>: hit windows of array column w. Texts hold no quotes."""
    found = []
    for width in sorted({k for k, _ in windows}):
        texts = sorted({t for k, t in windows if k == width})
        heads, tails = sorted({t.split(" ")[0] for t in texts}), sorted({t.split(" ")[-1] for t in texts})
        quoted = lambda xs: _in(f"'{x}'" for x in xs)
        here = f"array_join(slice({w}, i, {width}), ' ')"
        test = f"{w}[i - 1] IN {quoted(heads)} AND {w}[i + {width - 2}] IN {quoted(tails)} AND {here} IN {quoted(texts)}"
        found.append(f"transform(filter(if(size({w}) >= {width}, sequence(1, size({w}) - {width - 1}), cast(array() as array<int>)), i -> {test}), i -> struct(i, {width} as width, {here} as win))")
    return f"concat({', '.join(found)})" if found else "cast(array() as array<struct<i: int, width: int, win: string>>)"


def _n_hit(hits: str) -> str:
    """Number of positions covered by hits: sorted by place, each adds what reaches beyond the last end."""
    return (
        f"aggregate(array_sort(transform({hits}, h -> struct(h.i as i, h.i + h.width as e))), struct(0L as n, 0 as e), "
        "(a, h) -> struct(a.n + greatest(0, h.e - greatest(h.i, a.e)) as n, greatest(a.e, h.e) as e), a -> a.n)"
    )


HITS = "array<struct<i: int, width: int, win: string>>"


def with_hits(docs: DataFrame, benchmark: DataFrame, text_col: str, max_literals: int = 50_000, item_col: str = "item_id", bench_text: str = "text", broadcast: int = BROADCAST) -> tuple[DataFrame, str, DataFrame]:
    """(docs plus a struct: n_words, n_hit, wins, spans; its name; the benchmark's windows)."""
    windows = written(benchmark_windows(benchmark, item_col, bench_text), "windows")
    few = windows.select("width", "win").distinct().limit(max_literals + 1).collect()
    w, h = fresh("__words", docs), fresh("__hits", docs)
    if len(few) > max_literals:
        docs, hits = _probed_hits(docs, windows, text_col, broadcast)
        row = hits.columns[0]
        per = hits.groupBy(row).agg(F.collect_list(F.struct("i", "width", "win")).alias(h))
        out = docs.join(per, row, "left").drop(row).withColumn(w, words(F.col(text_col))).withColumn(h, F.coalesce(F.col(h), F.expr(f"cast(array() as {HITS})")))
    else:
        out = docs.withColumn(w, words(F.col(text_col))).withColumn(h, F.expr(_hits_expr([(r[0], r[1]) for r in few], w)))
    made = F.struct(F.size(w).cast("long").alias("n_words"), F.expr(_n_hit(h)).alias("n_hit"), F.expr(f"array_distinct(transform({h}, h -> h.win))").alias("wins"), F.expr(f"transform({h}, h -> struct(h.i as i, h.width as width))").alias("spans"))
    found = fresh("__found", docs)
    return out.withColumn(found, made).drop(w, h), found, windows


def _probed_hits(docs: DataFrame, windows: DataFrame, text_col: str, broadcast: int) -> tuple[DataFrame, DataFrame]:
    """(docs with a row number, first column; hits: row, i, width, win) by hashes of windows first, then by their texts."""
    row = fresh("__row", docs)
    docs = written(docs.select(F.monotonically_increasing_id().alias(row), "*"), "docs")
    distinct = windows.select("width", "win").distinct()
    hashes = windows.select("width", F.xxhash64("win").alias("h")).distinct()
    hashes = F.broadcast(hashes) if hashes.limit(broadcast + 1).count() <= broadcast else hashes
    w = docs.select(row, words(F.col(text_col)).alias("w"))
    widths = [r[0] for r in windows.select("width").distinct().collect()]  # at most N
    hit = None
    for width in widths:
        at = w.select(row, F.posexplode(F.expr(f"transform(if(size(w) >= {width}, sequence(1, size(w) - {width - 1}), cast(array() as array<int>)), i -> xxhash64(array_join(slice(w, i, {width}), ' ')))")).alias("p", "h"))
        at = at.join(hashes.where(f"width = {width}"), "h", "left_semi").select(row, (F.col("p") + 1).alias("i"), F.lit(width).alias("width"))
        hit = at if hit is None else hit.unionByName(at)
    places = written(hit, "places").groupBy(row).agg(F.collect_list(F.struct("i", "width")).alias("at"))
    texts = w.join(places, row).select(row, "w", F.inline("at")).select(row, "i", "width", F.array_join(F.slice("w", F.col("i"), F.col("width")), " ").alias("win"))
    return docs, written(texts.join(distinct, ["width", "win"], "left_semi").select(row, "i", "width", "win"), "hits")


def _contaminated(c: str) -> str:
    return f"({c}.n_hit > 0 and 20 * {c}.n_hit >= {c}.n_words)"


def contamination(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", max_literals: int = 50_000, broadcast: int = BROADCAST) -> DataFrame:
    """One row per document: id, n_words, n_hit, n_items, items_sha256, contaminated."""
    hit, c, windows = with_hits(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), benchmark, "text", max_literals, broadcast=broadcast)
    small = written(hit.select(F.monotonically_increasing_id().alias("row"), "id", f"{c}.n_words", f"{c}.n_hit", f"{c}.wins", F.expr(_contaminated(c)).alias("contaminated")), "hits")
    found = small.where("n_hit > 0").select("row", F.explode("wins").alias("win")).join(windows.select("win", "item"), "win")
    items = found.groupBy("row").agg(F.array_sort(F.collect_set("item")).alias("items"))
    out = small.drop("wins").join(items, "row", "left").withColumn("items", F.coalesce("items", F.array().cast("array<string>")))
    return out.select(F.col("id").alias(id_col), "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.encode(F.array_join("items", ","), "UTF-8"), 256).alias("items_sha256"), "contaminated")


def decontaminate(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", mode: str = "document", max_literals: int = 50_000, broadcast: int = BROADCAST) -> DataFrame:
    """mode "document" drops contaminated documents; "span" removes every hit word from the texts of documents with hits
    (their text becomes the remaining normalised words joined by a space); all other columns pass through."""
    hit, c, _ = with_hits(docs, benchmark, text_col, max_literals, broadcast=broadcast)
    # The row number keeps the filter above the window scan, which the optimizer would put in place of each use of c.
    hit = hit.withColumn(r := fresh("__number", hit), F.monotonically_increasing_id())
    if mode == "document":
        return hit.where(F.expr(f"{r} >= 0 and not {_contaminated(c)}")).select(*docs.columns)
    v, k = fresh("__all", hit), fresh("__kept", hit)
    kept = F.expr(f"filter(sequence(1, size({v})), k -> not exists({c}.spans, s -> k >= s.i and k < s.i + s.width))")
    left = F.expr(f"array_join(transform({k}, k -> {v}[k - 1]), ' ')")
    cut = hit.withColumn(v, words(F.col(text_col))).withColumn(k, F.when(F.expr(f"{c}.n_hit > 0"), kept))
    return cut.withColumn(text_col, F.when(F.expr(f"{c}.n_hit > 0"), left).otherwise(F.col(text_col))).select(*docs.columns)


def op7_decontaminate(spark, sf_dir: str) -> DataFrame:
    """All documents against all benchmark items."""
    docs, bench = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "benchmark"))
    return contamination(docs, bench)


OP7_SQL = r"""
WITH low AS (SELECT 'd' AS kind, doc_id::VARCHAR AS id, doc_id, text FROM documents UNION ALL SELECT 'b', item_id::VARCHAR, NULL, text FROM benchmark),
     t AS (SELECT kind, id, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM low),
     b AS (SELECT DISTINCT id AS item, k AS width, list_aggregate(w[i:i + k - 1], 'string_agg', ' ') AS win
           FROM (SELECT id, w, k, unnest(range(1, len(w) - k + 2)) AS i FROM (SELECT *, least(13, len(w)) AS k FROM t WHERE kind = 'b' AND len(w) > 0))),
     k AS (SELECT DISTINCT width FROM b),
     d AS (SELECT doc_id, width, i, list_aggregate(w[i:i + width - 1], 'string_agg', ' ') AS win
           FROM (SELECT doc_id, width, w, unnest(range(1, len(w) - width + 2)) AS i FROM t, k WHERE kind = 'd')),
     h AS (SELECT d.doc_id, d.i, d.width, b.item FROM d JOIN b USING (width, win)),
     p AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + width)) AS p FROM (SELECT DISTINCT doc_id, i, width FROM h)) GROUP BY 1),
     s AS (SELECT doc_id, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS items FROM h GROUP BY 1)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM t LEFT JOIN p USING (doc_id) LEFT JOIN s USING (doc_id) WHERE kind = 'd'
"""
