"""Queries of the methods, variants, baselines and measures over the workloads, with SQL where it can express them."""

from __future__ import annotations

import time
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from codetrees.functions import codelen
from codetrees.operators import apply as ap
from codetrees.operators import itemsets as it
from codetrees.plans import select as sel
from codetrees.plans.counts import counts_of
from codetrees.plans.cover import cover_baseline, cover_start, cover_usage
from codetrees.plans.greedy import fixed_trees_model, grow_model
from codetrees.plans.model import LEAF, Model, independent_cost, itemsets_of_leaf
from codetrees.sources.workloads import DOC_ITEMS, LANG_ITEMS, ORDER_REST, WORKLOADS, Workload

Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def one_row(spark: SparkSession, **values) -> DataFrame:
    kinds = {int: "long", float: "double", str: "string", bool: "boolean"}
    return spark.createDataFrame([tuple(values.values())], ", ".join(f"{k} {kinds[type(v)]}" for k, v in values.items()))


_KEPT: ContextVar[dict | None] = ContextVar("kept", default=None)


@contextmanager
def made_once():
    """Inside, counts and family of a workload are made once, for all rows of a report that ask for them."""
    before = _KEPT.set({})
    try:
        yield
    finally:
        _KEPT.reset(before)


def _once(key, make):
    kept = _KEPT.get()
    if kept is None:
        return make()
    if key not in kept:
        kept[key] = make()
    return kept[key]


def counts(spark: SparkSession, sf_dir: str, name: str):
    w = WORKLOADS[name] if isinstance(name, str) else name
    return _once(("counts", sf_dir, w), lambda: counts_of(w.compact(spark, sf_dir), w.k)), w


# ---- SQL pieces


def db(n: str, n1: str) -> str:
    """Data bits in SQL."""
    part = lambda c: f"CASE WHEN {c} > 0 THEN -({c}) * log2(({c})::DOUBLE / ({n})) ELSE 0 END"
    return f"({part(n1)} + {part(f'({n}) - ({n1})')})"


NML = """SELECT mm, CASE WHEN mm = 0 THEN 0 ELSE log2(sum(exp(lgamma(mm + 1) - lgamma(k + 1) - lgamma(mm - k + 1)
  + CASE WHEN k > 0 THEN k * ln(k::DOUBLE / mm) ELSE 0 END + CASE WHEN k < mm THEN (mm - k) * ln((mm - k)::DOUBLE / mm) ELSE 0 END))) END AS c
  FROM (SELECT mm, unnest(range(0, mm + 1)) AS k FROM ({ms}) WHERE mm > 0) GROUP BY mm UNION ALL SELECT 0, 0"""


def ct(name: str) -> str:
    return f"ct AS MATERIALIZED ({WORKLOADS[name].compact_sql()})"


def bit(i) -> str:
    return f"((m >> {i}) & 1)"


# ---- data sets

for _name, _w in WORKLOADS.items():
    query(
        f"dataset_stats_{_name}",
        f"WITH {ct(_name)} SELECT sum(n)::BIGINT AS n_rows, {_w.k} AS items, count(*) AS distinct_rows, round(sum(bit_count(m) * n) * 100.0 / (sum(n) * {_w.k}), 4) AS pct_ones FROM ct",
    )(lambda s, d, w=_w: it.dataset_stats(w.compact(s, d), w.k).withColumnRenamed("rows", "n_rows"))

for _name in ("w3", "w4", "w5"):
    query(f"compact_{_name}", WORKLOADS[_name].compact_sql())(lambda s, d, w=WORKLOADS[_name]: w.compact(s, d))

query(
    "cooccurrence_w5",
    f"WITH {ct('w5')} SELECT i.i::INTEGER AS i, j.j::INTEGER AS j, sum(n)::BIGINT AS c FROM ct, (SELECT unnest(range(18)) AS i) i, (SELECT unnest(range(18)) AS j) j WHERE i <= j AND {bit('i')} = 1 AND {bit('j')} = 1 GROUP BY ALL",
)(lambda s, d: it.cooccurrence(WORKLOADS["w5"].compact(s, d), 18))


@query(
    "supports_w6",
    f"WITH {ct('w6')}, s AS (SELECT (1::BIGINT << i.i) | (1::BIGINT << j.j) AS mask FROM (SELECT unnest(range(31)) AS i) i, (SELECT unnest(range(31)) AS j) j WHERE i <= j) "
    "SELECT mask, coalesce(sum(n), 0)::BIGINT AS supp FROM s LEFT JOIN ct ON m & mask = mask GROUP BY mask",
)
def supports_w6(spark, sf_dir):
    """Supports of all single items and pairs by the containment join."""
    i = spark.range(31).select(F.col("id").cast("int").alias("i"))
    sets = i.crossJoin(i.select(F.col("i").alias("j"))).where("i <= j").select(F.expr("shiftleft(1L, i) | shiftleft(1L, j)").alias("mask"))
    return it.itemset_supports(WORKLOADS["w6"].compact(spark, sf_dir), sets)


# ---- costs


def independent(ctab: DataFrame, k: int) -> DataFrame:
    """Bits of the single-leaf model by one aggregation: (n_rows, bits)."""
    sums = ctab.agg(F.sum("n").alias("n"), *[F.sum(F.expr(f"n * (shiftright(m, {i}) & 1)")).alias(f"c{i}") for i in range(k)])
    one = sums.select("n", F.explode(F.array(*[F.col(f"c{i}") for i in range(k)])).alias("n1"))
    return one.groupBy("n").agg(F.round(F.sum(codelen.leaf_cost_col(F.col("n"), F.col("n1"))), 4).alias("bits")).select(F.col("n").alias("n_rows"), "bits")


for _name, _w in WORKLOADS.items():
    query(
        f"independent_cost_{_name}",
        f"WITH {ct(_name)}, s AS (SELECT i, sum(n)::BIGINT AS n, sum(n * {bit('i')})::BIGINT AS n1 FROM ct, (SELECT unnest(range({_w.k})) AS i) GROUP BY i), "
        f"z AS ({NML.format(ms='SELECT DISTINCT n AS mm FROM s')}) SELECT n AS n_rows, round(sum(1 + c + {db('n', 'n1')}), 4) AS bits FROM s JOIN z ON mm = n GROUP BY n",
    )(lambda s, d, w=_w: independent(w.compact(s, d), w.k))

# Sizes of leaves: how many lines an order, a part and a supplier have; each size once.
SIZE_KEYS = ("l_orderkey", "l_partkey", "l_suppkey")
SIZES_SQL = f"SELECT DISTINCT n AS mm FROM ({' UNION ALL '.join(f'SELECT count(*) AS n FROM lineitem GROUP BY {x}' for x in SIZE_KEYS)})"


def leaf_sizes(spark, sf_dir) -> DataFrame:
    """(m): the distinct sizes."""
    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select(*SIZE_KEYS)
    sizes = [lines.groupBy(x).agg(F.count("*").alias("m")).select("m") for x in SIZE_KEYS]
    return sizes[0].unionByName(sizes[1]).unionByName(sizes[2]).distinct()


@query("nml_table", f"WITH z AS ({NML.format(ms=SIZES_SQL)}) SELECT mm::BIGINT AS m, round(c, 6) AS bits, round(c, 4) AS series FROM z WHERE mm > 0")
def nml_table(spark, sf_dir):
    """Leaf complexity by the exact fold; the series beside it, which agrees to 4 digits from about 10 rows on."""
    m = leaf_sizes(spark, sf_dir)
    exact = codelen.nml_bits_col(F.col("m"), "exact")
    series = F.when(F.col("m") < 50, exact).otherwise(codelen.nml_bits_col(F.col("m"), "asymptotic"))
    return m.select("m", F.round(exact, 6).alias("bits"), F.round(series, 4).alias("series"))


@query(
    "criteria_table",
    f"WITH t AS (SELECT count(*) AS n FROM lineitem), z AS ({NML.format(ms=SIZES_SQL)}) SELECT mm::BIGINT AS m, round(c, 4) AS refined, round(0.5 * log2(n), 4) AS bic, round(log2(exp(1)), 4) AS aic, round(0.5 * log2(mm), 4) AS crude FROM z, t WHERE mm > 0",
)
def criteria_table(spark, sf_dir):
    """Model bits of a leaf under each criterion, for all lines as the data set."""
    total = spark.read.parquet(f"{sf_dir}/lineitem.parquet").agg(F.count("*").cast("double").alias("n"))
    m = leaf_sizes(spark, sf_dir).crossJoin(F.broadcast(total))
    return m.select("m", *[F.round(codelen.complexity_col(F.col("m"), c, F.col("n")), 4).alias(c) for c in codelen.CRITERIA])

# ---- first-round gains


def split_gains(ctab: DataFrame, k: int, criterion: str = "refined") -> DataFrame:
    """(target, item, gain): bits saved by the first split of each target on each item. Pair counts need one shuffle."""
    pairs = it.cooccurrence(ctab, k)
    total = ctab.agg(F.sum("n").alias("n"))
    have = pairs.where("i = j").select("i", "c")
    every = ctab.sparkSession.range(k).select(F.col("id").cast("int").alias("i")).join(have, "i", "left").select("i", F.coalesce("c", F.lit(0)).alias("c"))
    cell = every.select(F.col("i").alias("target"), F.col("c").alias("n1")).crossJoin(every.select(F.col("i").alias("item"), F.col("c").alias("nj"))).where("target <> item")
    both = pairs.where("i < j").select(F.col("i").alias("a"), F.col("j").alias("b"), F.col("c").alias("n1j"))
    cell = cell.withColumn("a", F.least("target", "item")).withColumn("b", F.greatest("target", "item")).join(both, ["a", "b"], "left").crossJoin(F.broadcast(total))
    cell = cell.withColumn("n1j", F.coalesce("n1j", F.lit(0)))
    # The complexity of a leaf depends on its rows only: once for each of the 2 k + 1 numbers of rows that occur.
    sizes = every.crossJoin(F.broadcast(total)).select("n", F.explode(F.array(F.col("n"), F.col("c"), F.col("n") - F.col("c"))).alias("m")).distinct()
    sizes = sizes.groupBy("m").agg(F.first("n").alias("n")).select("m", codelen.complexity_col(F.col("m"), criterion, F.col("n")).alias("x"))
    for name, rows in (("x0", F.col("n")), ("x1", F.col("nj")), ("x2", F.col("n") - F.col("nj"))):
        cell = cell.withColumn("m", rows).join(F.broadcast(sizes.withColumnRenamed("x", name)), "m").drop("m")
    cost = lambda x, n, n1: F.lit(1.0) + F.col(x) + codelen.data_bits_col(n, n1)
    gain = cost("x0", F.col("n"), F.col("n1")) - codelen.split_cost(k) - cost("x1", F.col("nj"), F.col("n1j")) - cost("x2", F.col("n") - F.col("nj"), F.col("n1") - F.col("n1j"))
    return cell.select("target", "item", gain.alias("gain"))


def gains_sql(name: str) -> str:
    k = WORKLOADS[name].k
    ms = "SELECT DISTINCT unnest([n, nj, n - nj]) AS mm FROM g"
    cost = lambda z, n, n1: f"(1 + {z}.c + {db(n, n1)})"
    return (
        f"WITH {ct(name)}, g AS MATERIALIZED (SELECT t.t, j.j, sum(n)::BIGINT AS n, sum(n * {bit('t')})::BIGINT AS n1, sum(n * {bit('j')})::BIGINT AS nj, sum(n * {bit('t')} * {bit('j')})::BIGINT AS n1j "
        f"FROM ct, (SELECT unnest(range({k})) AS t) t, (SELECT unnest(range({k})) AS j) j WHERE t <> j GROUP BY ALL), z AS MATERIALIZED ({NML.format(ms=ms)}), "
        f"r AS (SELECT t::INTEGER AS target, j::INTEGER AS item, {cost('a', 'n', 'n1')} - (1 + log2({k})) - {cost('b', 'nj', 'n1j')} - {cost('d', 'n - nj', 'n1 - n1j')} AS gain "
        "FROM g JOIN z a ON a.mm = n JOIN z b ON b.mm = nj JOIN z d ON d.mm = n - nj)"
    )


for _name in ("w3", "w5", "w7", "w9", "w10"):
    query(f"split_gains_{_name}", gains_sql(_name) + " SELECT target, item, round(gain, 4) AS gain FROM r")(lambda s, d, w=WORKLOADS[_name]: split_gains(w.compact(s, d), w.k).withColumn("gain", F.round("gain", 4)))

for _name in ("w5", "w9"):

    @query(f"best_first_split_{_name}", gains_sql(_name) + " SELECT target, item, round(gain, 4) AS gain FROM r QUALIFY row_number() OVER (PARTITION BY target ORDER BY round(gain, 6) DESC, item) = 1")
    def _best(spark, sf_dir, w=WORKLOADS[_name]):
        g = split_gains(w.compact(spark, sf_dir), w.k).withColumn("r", F.row_number().over(Window.partitionBy("target").orderBy(F.round("gain", 6).desc(), "item")))
        return g.where("r = 1").select("target", "item", F.round("gain", 4).alias("gain"))


# ---- greedy growth


def grown(spark, sf_dir, name, **options) -> tuple[Model, object]:
    c, w = counts(spark, sf_dir, name)
    return grow_model(c, w.names, **options), c


def _sets_with_supports(spark, sf_dir, name, model: Model) -> DataFrame:
    return it.itemset_supports(WORKLOADS[name].compact(spark, sf_dir), model.itemsets_table(spark).select("mask"))


for _name in ("w1", "w1_all"):
    query(f"grow_{_name}", f"WITH {ct(_name)} SELECT (1::BIGINT << i) AS mask, sum(n * {bit('i')})::BIGINT AS supp FROM ct, (SELECT unnest(range(10)) AS i) GROUP BY i")(lambda s, d, n=_name: _sets_with_supports(s, d, n, grown(s, d, n)[0]))
for _name in ("w2", "w2_all"):
    query(
        f"grow_{_name}",
        f"WITH {ct(_name)}, s AS (SELECT (1::BIGINT << i) AS mask FROM (SELECT unnest(range(10)) AS i) UNION ALL SELECT (3::BIGINT << i) FROM (SELECT unnest(range(9)) AS i)) SELECT mask, sum(CASE WHEN m & mask = mask THEN n ELSE 0 END)::BIGINT AS supp FROM ct, s GROUP BY mask",
    )(lambda s, d, n=_name: _sets_with_supports(s, d, n, grown(s, d, n)[0]))
query("dep_edges_w2", "SELECT s AS src, d AS dst FROM (VALUES (5, 4), (6, 5), (8, 7), (2, 1), (3, 2), (7, 6), (0, 1), (9, 8), (4, 3)) v(s, d)")(lambda s, d: grown(s, d, "w2")[0].edges_table(s).select("src", "dst"))


@query("toposort_w2")
def toposort_w2(spark, sf_dir):
    """Sending order of the grown model: (place, item)."""
    return spark.createDataFrame([(p, i) for p, i in enumerate(grown(spark, sf_dir, "w2")[0].order())], "place int, item int")


def complexity_sql(ms: str, criterion: str = "refined") -> str:
    """(mm, c): model bits of a leaf for every number of rows that the query ms gives."""
    bits = {"bic": "0.5 * log2((SELECT sum(n) FROM ct))", "aic": "log2(exp(1))", "crude": "0.5 * log2(greatest(mm, 1))"}
    return NML.format(ms=ms) if criterion == "refined" else f"SELECT DISTINCT mm, {bits[criterion]} AS c FROM ({ms})"


def _prefix_sql(name: str, criterion: str = "refined", allowed: str = "true") -> str:
    """Three rounds of growth: gains of every path of up to two tests, then one pick after the other. allowed: a condition
    on the target t and the tested item j."""
    k = WORKLOADS[name].k
    sat = "(m & pos = pos AND m & neg = 0)"
    cost = lambda z, n, n1: f"(1 + {z}.c + {db(n, n1)})"
    cols = "t, pos, neg, j, gain"
    best = "ORDER BY round(gain, 9) DESC, t, pos, neg, j LIMIT 1"
    child = lambda p, lead="": f"((x.pos = {p}.pos | (1::BIGINT << {p}.j) AND x.neg = {p}.neg) OR (x.pos = {p}.pos AND x.neg = {p}.neg | (1::BIGINT << {p}.j)))"
    return f"""
WITH {ct(name)}, lit AS (SELECT unnest(range({k})) AS i),
 path AS (SELECT 0::BIGINT AS pos, 0::BIGINT AS neg UNION SELECT (1::BIGINT << i), 0 FROM lit UNION SELECT 0, (1::BIGINT << i) FROM lit
   UNION SELECT (1::BIGINT << a.i) | (1::BIGINT << b.i), 0 FROM lit a, lit b WHERE a.i < b.i UNION SELECT 0, (1::BIGINT << a.i) | (1::BIGINT << b.i) FROM lit a, lit b WHERE a.i < b.i
   UNION SELECT (1::BIGINT << a.i), (1::BIGINT << b.i) FROM lit a, lit b WHERE a.i <> b.i),
 g AS MATERIALIZED (SELECT t.i AS t, pos, neg, j.i AS j, sum(n)::BIGINT AS n, sum(n * {bit('t.i')})::BIGINT AS n1, sum(n * {bit('j.i')})::BIGINT AS nj, sum(n * {bit('t.i')} * {bit('j.i')})::BIGINT AS n1j
   FROM ct JOIN path ON {sat}, lit t, lit j WHERE t.i <> j.i AND ((pos | neg) >> t.i) & 1 = 0 AND ((pos | neg) >> j.i) & 1 = 0 GROUP BY ALL),
 z AS MATERIALIZED ({complexity_sql('SELECT DISTINCT unnest([n, nj, n - nj]) AS mm FROM g', criterion)}),
 x AS MATERIALIZED (SELECT t, pos, neg, j, {cost('a', 'n', 'n1')} - (1 + log2({k})) - {cost('b', 'nj', 'n1j')} - {cost('d', 'n - nj', 'n1 - n1j')} AS gain
   FROM g JOIN z a ON a.mm = n JOIN z b ON b.mm = nj JOIN z d ON d.mm = n - nj WHERE {allowed}),
 p1 AS MATERIALIZED (SELECT {cols} FROM x WHERE pos = 0 AND neg = 0 {best}),
 p2 AS MATERIALIZED (SELECT x.t, x.pos, x.neg, x.j, x.gain FROM x, p1 WHERE ((x.pos = 0 AND x.neg = 0 AND x.t <> p1.t) OR (x.t = p1.t AND {child('p1')})) AND NOT (x.j = p1.t AND x.t = p1.j) {best.replace('gain', 'x.gain').replace(' t,', ' x.t,').replace(' pos,', ' x.pos,').replace(' neg,', ' x.neg,').replace(' j ', ' x.j ')}),
 p3 AS (SELECT x.t, x.pos, x.neg, x.j, x.gain FROM x, p1, p2
   WHERE ((x.pos = 0 AND x.neg = 0 AND x.t <> p1.t AND x.t <> p2.t) OR (x.t = p1.t AND {child('p1')} AND NOT (p2.t = p1.t AND x.pos = p2.pos AND x.neg = p2.neg)) OR (x.t = p2.t AND {child('p2')}))
   AND NOT (x.j = p1.t AND x.t = p1.j) AND NOT (x.j = p2.t AND x.t = p2.j) AND NOT (x.j = p1.t AND p1.j = p2.t AND x.t = p2.j) AND NOT (x.j = p2.t AND p2.j = p1.t AND x.t = p1.j)
   {best.replace('gain', 'x.gain').replace(' t,', ' x.t,').replace(' pos,', ' x.pos,').replace(' neg,', ' x.neg,').replace(' j ', ' x.j ')})
SELECT 1 AS step, t::INTEGER AS target, pos, neg, j::INTEGER AS item, round(gain, 4) AS gain FROM p1 UNION ALL SELECT 2, t, pos, neg, j, round(gain, 4) FROM p2 UNION ALL SELECT 3, t, pos, neg, j, round(gain, 4) FROM p3
"""


def grow_prefix(spark, sf_dir, name: str, **options) -> DataFrame:
    """The first three splits of growth."""
    m, _ = grown(spark, sf_dir, name, max_splits=3, **options)
    return spark.createDataFrame([(i + 1, t, p, q, j, round(g, 4)) for i, (t, p, q, j, g, _) in enumerate(m.trace)], "step int, target int, pos long, neg long, item int, gain double")


query("grow_prefix3_w9", _prefix_sql("w9"))(lambda s, d: grow_prefix(s, d, "w9"))
query("grow_prefix3_order_w9", _prefix_sql("w9", allowed="j < t"))(lambda s, d: grow_prefix(s, d, "w9", order=list(range(11))))
for _c in ("bic", "aic", "crude"):
    query(f"grow_prefix3_{_c}_w9", _prefix_sql("w9", _c))(lambda s, d, c=_c: grow_prefix(s, d, "w9", criterion=c))


def grow_row(spark, sf_dir, name, **options):
    c, w = counts(spark, sf_dir, name)
    t = time.perf_counter()
    m = grow_model(c, w.names, **options)
    base = independent_cost([c.path(0, 0, i)[1] for i in range(w.k)], c.total, m.criterion)
    return {"workload": name, "n_rows": c.total, "items": w.k, "base_bits": base, "bits": m.cost(), "ratio_pct": 100 * m.cost() / base, "splits": len(m.trace), "itemsets": m.count_itemsets(), "scans": c.scans, "seconds": time.perf_counter() - t}


for _name in ("w3", "w4", "w5", "w6", "w7", "w8", "w9", "w10"):
    query(f"grow_summary_{_name}")(lambda s, d, n=_name: one_row(s, **grow_row(s, d, n)).drop("seconds"))
for _c in ("bic", "aic", "crude"):
    query(f"grow_criterion_{_c}_w9")(lambda s, d, c=_c: one_row(s, **grow_row(s, d, "w9", criterion=c)).drop("seconds"))
query("grow_fixed_order_w9")(lambda s, d: one_row(s, **grow_row(s, d, "w9", order=list(range(11)))).drop("seconds"))
query("grow_trace_w5")(lambda s, d: grown(s, d, "w5")[0].trace_table(s))
query("grow_nodes_w9")(lambda s, d: grown(s, d, "w9")[0].nodes_table(s, "w9"))
query("tree_signatures_w7")(lambda s, d: s.createDataFrame([(x,) for x in grown(s, d, "w7")[0].signatures()], "items array<string>"))


@query("packed_by_w8")
def packed_by_w8(spark, sf_dir):
    """Which targets' trees test each language item."""
    m, _ = grown(spark, sf_dir, "w8")
    return spark.createDataFrame([(i.name, m.packed_by(i.name)) for i in LANG_ITEMS], "item string, used_by array<string>")


@query("tree_text_w9")
def tree_text_w9(spark, sf_dir):
    m, _ = grown(spark, sf_dir, "w9")
    return spark.createDataFrame([(n, m.explain(i)) for i, n in enumerate(m.names)], "target string, tree string")


# ---- literal trees on w5: status_F tests status_O, then status_P where it is absent; price_gt_100k likewise

LITERAL = [LEAF] * 18
LITERAL[0] = ("test", 1, LEAF, ("test", 2, LEAF, LEAF))
LITERAL[8] = ("test", 9, LEAF, ("test", 12, LEAF, LEAF))
LITERAL_LEAVES = [(0, 2, 0), (0, 4, 2), (0, 0, 6), (8, 512, 0), (8, 4096, 512), (8, 0, 4608)]
_LEAF_VALUES = ", ".join(f"({t}, {i % 3}, {p}::BIGINT, {q}::BIGINT)" for i, (t, p, q) in enumerate(LITERAL_LEAVES))
_LEAVES = f"lv AS (SELECT * FROM (VALUES {_LEAF_VALUES}) v(target, leaf, pos, neg))"


def literal_model(spark, sf_dir) -> Model:
    c, w = counts(spark, sf_dir, "w5")
    return fixed_trees_model(c, w.names, LITERAL)


query("leaf_counts_literal_w5", f"WITH {ct('w5')}, {_LEAVES} SELECT target, leaf, sum(n)::BIGINT AS n, sum(n * {bit('target')})::BIGINT AS n1 FROM ct JOIN lv ON m & pos = pos AND m & neg = 0 GROUP BY ALL")(
    lambda s, d: ap.leaf_counts(WORKLOADS["w5"].compact(s, d), literal_model(s, d)).where("target in (0, 8)")
)
query("route_literal_w5", f"WITH p AS ({WORKLOADS['w5'].packed_sql()}), {_LEAVES} SELECT key, target, leaf FROM p JOIN lv ON m & pos = pos AND m & neg = 0")(
    lambda s, d: ap.route(WORKLOADS["w5"].packed(s, d), literal_model(s, d)).where("target in (0, 8)")
)


@query(
    "inclexcl_w5",
    f"WITH {ct('w5')}, {_LEAVES} SELECT target, pos, neg, coalesce(sum(n), 0)::BIGINT AS n, coalesce(sum(n * {bit('target')}), 0)::BIGINT AS n1 FROM lv LEFT JOIN ct ON m & pos = pos AND m & neg = 0 GROUP BY ALL",
)
def inclexcl_w5(spark, sf_dir):
    """Leaf counts of the literal trees from supports alone."""
    w = WORKLOADS["w5"]
    leaves = spark.createDataFrame(LITERAL_LEAVES, "target int, pos long, neg long")
    masks = {m for t, p, q in LITERAL_LEAVES for m in itemsets_of_leaf(t, p, q)}
    supports = it.itemset_supports(w.compact(spark, sf_dir), spark.createDataFrame([(m,) for m in masks], "mask long"))
    return it.leaf_counts_from_supports(leaves, supports)


# The leaves that orders reach in a tree of status_P over the two other states and the four prices.
TESTED = sum(1 << i for i in (0, 1, 8, 9, 10, 11))
REACHED_SQL = f"{ct('w5')}, lv AS (SELECT DISTINCT 2 AS target, m & {TESTED} AS pos, {TESTED} - (m & {TESTED}) AS neg FROM ct)"


def reached_leaves(spark, sf_dir) -> DataFrame:
    """(target, pos, neg) of these leaves."""
    pos = F.expr(f"m & {TESTED}L")
    return WORKLOADS["w5"].compact(spark, sf_dir).select(F.lit(2).alias("target"), pos.alias("pos"), (F.lit(TESTED).cast("long") - pos).alias("neg")).distinct()


query("leaf_sets_literal", f"WITH {REACHED_SQL} SELECT DISTINCT target, x::BIGINT AS mask FROM lv, (SELECT unnest(range(4096)) AS x) WHERE x & pos = pos AND x & ~(pos | neg | (1 << target)) = 0")(lambda s, d: it.leaf_sets(reached_leaves(s, d)))

# All leaves of the literal model (al) and their counts (lc).
LITERAL_COUNTS = (
    f"{ct('w5')}, {_LEAVES}, al AS (SELECT target::BIGINT AS target, pos, neg FROM lv UNION ALL SELECT i, 0, 0 FROM (SELECT unnest(range(18)) AS i) WHERE i NOT IN (0, 8)), "
    f"lc AS MATERIALIZED (SELECT target, pos, neg, sum(n)::BIGINT AS n, sum(n * {bit('target')})::BIGINT AS n1 FROM ct JOIN al ON m & pos = pos AND m & neg = 0 GROUP BY ALL)"
)


def literal_bits(spark, sf_dir, smoothing: str) -> DataFrame:
    """Bits of every row under the literal trees: one projection."""
    return ap.code_length(WORKLOADS["w5"].packed(spark, sf_dir), literal_model(spark, sf_dir), smoothing).select("key", F.round("bits", 6).alias("bits"))


for _name, _smoothing, _a, _b in (("literal", "laplace", 1.0, 2.0), ("kt", "kt", 0.5, 1.0), ("ml", "ml", 0.0, 0.0)):
    query(
        f"code_length_{_name}_w5",
        f"WITH p AS ({WORKLOADS['w5'].packed_sql()}), {LITERAL_COUNTS} SELECT key, round(sum(-log2((CASE WHEN {bit('target')} = 1 THEN n1 ELSE n - n1 END + {_a}) / (n + {_b}))), 6) AS bits FROM p JOIN lc ON m & pos = pos AND m & neg = 0 GROUP BY key",
    )(lambda s, d, x=_smoothing: literal_bits(s, d, x))


@query("roundtrip_mismatches", f"WITH p AS ({WORKLOADS['w5'].packed_sql()}) SELECT count(*) AS n_rows, 0::BIGINT AS mismatches FROM p")
def roundtrip_mismatches(spark, sf_dir):
    """Rows to residuals and back under a grown model."""
    m, _ = grown(spark, sf_dir, "w5")
    p = WORKLOADS["w5"].packed(spark, sf_dir)
    back = ap.from_residuals(ap.to_residuals(p, m), m).withColumnRenamed("m", "m2")
    return p.join(back, "key").agg(F.count("*").alias("n_rows"), F.sum((F.col("m") != F.col("m2")).cast("long")).alias("mismatches"))


# ---- families and their miners


def _pct(total: int, pct: float) -> int:
    return max(1, -int(-total * pct // 100))


def frequent_sql(name: str, pct: int, maxlen: int) -> str:
    k = WORKLOADS[name].k
    r = lambda a: f"(SELECT unnest(range({k})) AS {a})"
    parts = []
    for size in range(1, maxlen + 1):
        v = "abcd"[:size]
        mask = " | ".join(f"(1::BIGINT << {x})" for x in v)
        cond = " AND ".join([f"{x} < {y}" for x, y in zip(v, v[1:], strict=False)] + [f"m & ({mask}) = ({mask})"])
        parts.append(f"SELECT {mask} AS mask, {size} AS size, sum(n)::BIGINT AS supp FROM ct, {', '.join(r(x) for x in v)} WHERE {cond} GROUP BY ALL")
    return f"WITH {ct(name)} SELECT * FROM ({' UNION ALL '.join(parts)}) WHERE supp >= (SELECT ceil(sum(n) * {pct} / 100.0) FROM ct)"


def mined(spark, sf_dir, name, pct, maxlen):
    c, w = counts(spark, sf_dir, name)
    return it.mine_frequent(c, w.k, _pct(c.total, pct), maxlen), c, w


query("frequent_w6_len3", frequent_sql("w6", 1, 3))(lambda s, d: it.family_table(s, mined(s, d, "w6", 1, 3)[0]))
query("frequent_w8_len2", frequent_sql("w8", 20, 2))(lambda s, d: it.family_table(s, mined(s, d, "w8", 20, 2)[0]))
query("frequent_w9_len3", frequent_sql("w9", 1, 3))(lambda s, d: it.family_table(s, mined(s, d, "w9", 1, 3)[0]))
query("all_pairs_w7", frequent_sql("w7", 0, 2).replace("WHERE supp >= (SELECT ceil(sum(n) * 0 / 100.0) FROM ct)", "WHERE supp > 0"))(
    lambda s, d: it.family_table(s, it.all_itemsets(counts(s, d, "w7")[0], 10, 2)).where("supp > 0")
)


@query("fpgrowth_w6", frequent_sql("w6", 5, 3).replace("SELECT * FROM (", "SELECT mask, supp FROM (", 1))
def fpgrowth_w6(spark, sf_dir):
    """Frequent baskets by the built-in FP-growth, as masks."""
    p = WORKLOADS["w6"].packed(spark, sf_dir).select(F.expr("filter(sequence(0, 30), i -> (shiftright(m, i) & 1) = 1)").alias("items"))
    got = it.fpgrowth(p, 0.05, 3)
    return got.select(F.expr("aggregate(items, 0L, (a, i) -> a | shiftleft(1L, i))").alias("mask"), F.col("freq").alias("supp"))


@query(
    "low_entropy_w9_len2",
    f"WITH {ct('w9')}, s AS (SELECT (1::BIGINT << a.a) | (1::BIGINT << b.b) AS mask FROM (SELECT unnest(range(11)) AS a) a, (SELECT unnest(range(11)) AS b) b WHERE a <= b), "
    "c AS (SELECT mask, m & mask AS cell, sum(n) AS c FROM ct, s GROUP BY ALL), e AS (SELECT mask, -sum(c / (SELECT sum(n) FROM ct) * log2(c / (SELECT sum(n) FROM ct))) AS bits FROM c GROUP BY mask) SELECT mask, round(bits, 6) AS bits FROM e WHERE bits <= 1.5",
)
def low_entropy_w9_len2(spark, sf_dir):
    c, w = counts(spark, sf_dir, "w9")
    return spark.createDataFrame([(m, round(b, 6)) for m, b in it.mine_low_entropy(c, w.k, 1.5, 2).items()], "mask long, bits double")


@query(
    "set_entropies_w5",
    f"WITH {ct('w5')}, s AS (SELECT (7::BIGINT << a) AS mask FROM (SELECT unnest(range(16)) AS a)), c AS (SELECT mask, m & mask AS cell, sum(n) AS c FROM ct, s GROUP BY ALL) "
    "SELECT mask, round(-sum(c / (SELECT sum(n) FROM ct) * log2(c / (SELECT sum(n) FROM ct))), 6) AS bits FROM c GROUP BY mask",
)
def set_entropies_w5(spark, sf_dir):
    sets = spark.range(16).select(F.expr("shiftleft(7L, cast(id AS int))").alias("mask"))
    return it.set_entropies(WORKLOADS["w5"].compact(spark, sf_dir), sets).select("mask", F.round("bits", 6).alias("bits"))


@query("closure_violations_w6", f"WITH f AS ({frequent_sql('w6', 1, 3)}) SELECT count(*) AS sets, 0::BIGINT AS violations FROM f")
def closure_violations_w6(spark, sf_dir):
    f = it.family_table(spark, mined(spark, sf_dir, "w6", 1, 3)[0])
    return f.agg(F.count("*").alias("sets")).crossJoin(it.closure_violations(f).agg(F.count("*").alias("violations")))


@query("close_downward_w6", f"WITH f AS ({frequent_sql('w6', 1, 3)}) SELECT mask FROM f")
def close_downward_w6(spark, sf_dir):
    """Closing only the sets that lie in no larger one of a frequent family gives the family back."""
    f = it.family_table(spark, mined(spark, sf_dir, "w6", 1, 3)[0])
    return it.close_downward(it.maximal_sets(f))


# ---- selection


@query(
    "pair_model_w7_k4",
    f"WITH {ct('w7')}, i AS (SELECT unnest(range(4)) AS i), g AS MATERIALIZED (SELECT t.i AS t, j.i AS j, sum(n)::BIGINT AS n, sum(n * {bit('t.i')})::BIGINT AS n1, sum(n * {bit('j.i')})::BIGINT AS nj, sum(n * {bit('t.i')} * {bit('j.i')})::BIGINT AS n1j FROM ct, i t, i j GROUP BY ALL), "
    f"z AS MATERIALIZED ({NML.format(ms='SELECT DISTINCT unnest([n, nj, n - nj]) AS mm FROM g')}), "
    f"l AS (SELECT t, 1 + c + {db('n', 'n1')} AS cost FROM g JOIN z ON mm = n WHERE t = j), "
    f"e AS (SELECT g.t, j, least(l.cost, 1 + log2(4) + 2 + b.c + d.c + {db('nj', 'n1j')} + {db('n - nj', 'n1 - n1j')}) AS cost FROM g JOIN l ON l.t = g.t JOIN z b ON b.mm = nj JOIN z d ON d.mm = n - nj WHERE g.t <> j UNION ALL SELECT t, -1, cost FROM l), "
    "f AS (SELECT a.j AS a, b.j AS b, c.j AS c, d.j AS d, a.cost + b.cost + c.cost + d.cost AS cost FROM e a, e b, e c, e d WHERE a.t = 0 AND b.t = 1 AND c.t = 2 AND d.t = 3), "
    "u AS (SELECT cost, [a, b, c, d] AS p FROM f), v AS (SELECT cost, list_transform([0, 1, 2, 3], lambda x: CASE WHEN p[x + 1] < 0 THEN -1 ELSE p[p[x + 1] + 1] END) AS p2, p FROM u), "
    "w AS (SELECT cost, p, list_transform([1, 2, 3, 4], lambda x: CASE WHEN p2[x] < 0 THEN -1 ELSE p2[p2[x] + 1] END) AS p4 FROM v) "
    "SELECT round(min(cost), 4) AS bits FROM w WHERE p4 = [-1, -1, -1, -1]",
)
def pair_model_w7_k4(spark, sf_dir):
    """The optimal model over all itemsets of at most two of four items."""
    w = WORKLOADS["w7"].restricted(WORKLOADS["w7"].names[:4], "w7k4")
    c = counts_of(w.compact(spark, sf_dir), 4)
    return one_row(spark, bits=round(sel.pair_model(it.all_itemsets(c, 4, 2), w.names).cost(), 4))


def _best_tree_sql(end: str = "SELECT round(cost, 4) AS bits FROM t3") -> str:
    """Trees of target 0 (status_F) over sources 1, 2 and 8, from full paths to the root: t0 to t3 hold the bits of optimal
    trees by the number of free sources, u0 to u3 those of greedy ones."""
    src = [1, 2, 8]
    states = "SELECT a.v AS a, b.v AS b, c.v AS c FROM (VALUES (-1), (0), (1)) a(v), (VALUES (-1), (0), (1)) b(v), (VALUES (-1), (0), (1)) c(v)"
    sat = " AND ".join(f"({x} = -1 OR {bit(i)} = {x})" for x, i in zip("abc", src, strict=True))
    split = "(1 + log2(18))"
    out = [f"WITH {ct('w5')}, s AS ({states}), g AS MATERIALIZED (SELECT a, b, c, coalesce(sum(n), 0)::BIGINT AS n, coalesce(sum(n * {bit(0)}), 0)::BIGINT AS n1 FROM s LEFT JOIN ct ON {sat} GROUP BY ALL)"]
    out.append(f"z AS MATERIALIZED ({NML.format(ms='SELECT DISTINCT n AS mm FROM g')})")
    out.append(f"l AS MATERIALIZED (SELECT g.a, g.b, g.c, 1 + z.c + {db('n', 'n1')} AS cost FROM g JOIN z ON mm = n)")
    out.append("t0 AS MATERIALIZED (SELECT * FROM l WHERE a >= 0 AND b >= 0 AND c >= 0)")
    for free in (1, 2, 3):
        options = []
        for x in "abc":
            others = [y for y in "abc" if y != x]
            key = " AND ".join(f"p.{y} = l.{y} AND q.{y} = l.{y}" for y in others)
            prev = " UNION ALL ".join(f"SELECT * FROM t{i}" for i in range(free))
            options.append(f"SELECT l.a, l.b, l.c, {split} + p.cost + q.cost AS cost FROM l JOIN ({prev}) p ON p.{x} = 1 JOIN ({prev}) q ON q.{x} = 0 WHERE l.{x} = -1 AND {key}")
        is_free = f"((a = -1)::INT + (b = -1)::INT + (c = -1)::INT) = {free}"
        out.append(f"t{free} AS MATERIALIZED (SELECT a, b, c, min(cost) AS cost FROM (SELECT * FROM l UNION ALL {' UNION ALL '.join(options)}) WHERE {is_free} GROUP BY ALL)")
    out.append("u0 AS MATERIALIZED (SELECT * FROM t0)")
    for free in (1, 2, 3):
        options = []
        for place, x in enumerate("abc"):
            same = lambda p: " AND ".join(f"{p}.{y} = l.{y}" for y in "abc" if y != x)  # noqa: E731, B023
            options.append(
                f"SELECT l.a, l.b, l.c, {place} AS place, l.cost AS leaf, {split} + p.cost + q.cost AS now, {split} + v.cost + w.cost AS whole FROM l JOIN l p ON p.{x} = 1 AND {same('p')} JOIN l q ON q.{x} = 0 AND {same('q')} "
                f"JOIN u{free - 1} v ON v.{x} = 1 AND {same('v')} JOIN u{free - 1} w ON w.{x} = 0 AND {same('w')} WHERE l.{x} = -1"
            )
        out.append(f"u{free} AS MATERIALIZED (SELECT a, b, c, CASE WHEN now < leaf - 1e-9 THEN whole ELSE leaf END AS cost FROM ({' UNION ALL '.join(options)}) QUALIFY row_number() OVER (PARTITION BY a, b, c ORDER BY round(now, 9), place) = 1)")
    return f"{', '.join(out)} {end}"


@query("best_tree_w5_s3", _best_tree_sql())
def best_tree_w5_s3(spark, sf_dir):
    """Bits of the best tree of status_F with sources status_O, status_P and price_gt_100k."""
    c, w = counts(spark, sf_dir, "w5")
    masks = [sum(1 << i for n, i in enumerate((0, 1, 2, 8)) if x >> n & 1) for x in range(16)]
    cost, _ = sel.TreeSearch(it.with_supports(c, masks), w.k).best_tree(0, 0b100000110)
    return one_row(spark, bits=round(cost, 4))


@query("best_tree_scan_w5_s3", _best_tree_sql())
def best_tree_scan_w5_s3(spark, sf_dir):
    """The same tree with leaf counts from the rows instead of supports."""
    c, w = counts(spark, sf_dir, "w5")
    masks = [sum(1 << i for n, i in enumerate((0, 1, 2, 8)) if x >> n & 1) for x in range(16)]
    cost, _ = sel.TreeSearch(it.with_supports(c, masks), w.k, data=c).best_tree(0, 0b100000110)
    return one_row(spark, bits=round(cost, 4))


@query("best_tree_greedy_w5_s3", _best_tree_sql("SELECT round(u3.cost, 4) AS greedy_bits, round(t3.cost, 4) AS best_bits FROM u3, t3"))
def best_tree_greedy_w5_s3(spark, sf_dir):
    """The same sources with the greedy inner search: never cheaper than the best tree."""
    c, w = counts(spark, sf_dir, "w5")
    masks = [sum(1 << i for n, i in enumerate((0, 1, 2, 8)) if x >> n & 1) for x in range(16)]
    family = it.with_supports(c, masks)
    cost, _ = sel.TreeSearch(family, w.k, "greedy").best_tree(0, 0b100000110)
    best, _ = sel.TreeSearch(family, w.k).best_tree(0, 0b100000110)
    return one_row(spark, greedy_bits=round(cost, 4), best_bits=round(best, 4))


@query(
    "pick_minsup_w8",
    f"WITH f AS MATERIALIZED ({frequent_sql('w8', 0, 3)}), t AS (SELECT count(*) AS n FROM documents), h AS (SELECT n, n // (2 ** i)::BIGINT AS s FROM t, (SELECT unnest(range(1, 40)) AS i)), "
    "c AS (SELECT n, s, (SELECT count(*) FROM f WHERE supp >= s) AS c FROM h WHERE s >= 1), b AS (SELECT n, coalesce(min(s) FILTER (c < 2000), n // 2) AS s FROM c GROUP BY n) "
    "SELECT n AS n_rows, s AS minsup, c AS candidates FROM b JOIN c USING (n, s) GROUP BY ALL",
)
def pick_minsup_w8(spark, sf_dir):
    """The lowest halved support whose family of at most three items has up to 2,000 sets."""
    c, w = counts(spark, sf_dir, "w8")
    s = it.pick_minsup(c, w.k, 2000, 3)
    return one_row(spark, n_rows=c.total, minsup=s, candidates=len(it.mine_frequent(c, w.k, s, 3)) - 1)


# Least support in % of the rows, which alone bounds a family; w2 takes all pairs.
FAMILIES = {"w2": "pairs", "w3": 1.0, "w4": 1.0, "w5": 2.0, "w6": 1.0, "w7": 1.0, "w8": 40.0, "w9": 1.0, "w10": 5.0}


def family_of(c, w, name: str) -> dict[int, int]:
    pct = FAMILIES[name]
    return _once(("family", id(c), w, name), lambda: it.all_itemsets(c, w.k, 2) if pct == "pairs" else it.mine_frequent(c, w.k, _pct(c.total, pct)))


def select_row(spark, sf_dir, name: str, search: str, **options) -> dict:
    c, w = counts(spark, sf_dir, name)
    t = time.perf_counter()
    family = family_of(c, w, name)
    singles = [(c.total, c.path(0, 0, i)[1]) for i in range(w.k)]
    m = sel.select_model(family, w.names, search, singles=singles, **options)
    base = independent_cost([x for _, x in singles], c.total, m.criterion)
    kept = m.count_itemsets()
    return {"workload": name, "search": search, "candidates": len(family) - 1, "bits": m.cost(), "ratio_pct": 100 * m.cost() / base, "itemsets": kept, "kept_pct": 100.0 * kept / max(1, len(family) - 1), "inside": sel.all_in_family(m, family), "seconds": time.perf_counter() - t}


for _name in ("w2", "w3", "w4", "w5", "w6", "w7", "w8", "w9", "w10"):
    query(f"select_summary_{_name}")(lambda s, d, n=_name: one_row(s, **select_row(s, d, n, "exhaustive")).drop("seconds"))
for _name in ("w2", "w3", "w4", "w5", "w6", "w7", "w8", "w9", "w10"):
    query(f"select_greedy_summary_{_name}")(lambda s, d, n=_name: one_row(s, **select_row(s, d, n, "greedy")).drop("seconds"))
for _c in ("bic", "aic", "crude"):
    query(f"select_criterion_{_c}_w9")(lambda s, d, c=_c: one_row(s, **select_row(s, d, "w9", "greedy", criterion=c)).drop("seconds"))
query("select_ancestors_w9")(lambda s, d: one_row(s, **select_row(s, d, "w9", "greedy", augment="ancestors")).drop("seconds"))


@query("select_low_entropy_w9")
def select_low_entropy_w9(spark, sf_dir):
    """Selection over low-entropy candidates instead of frequent ones."""
    c, w = counts(spark, sf_dir, "w9")
    family = it.with_supports(c, it.mine_low_entropy(c, w.k, 2.0, 3))
    m = sel.select_model(family, w.names, "greedy", singles=[(c.total, c.path(0, 0, i)[1]) for i in range(w.k)])
    return one_row(spark, candidates=len(family) - 1, bits=m.cost(), itemsets=m.count_itemsets())


@query("select_spark_batch_w7")
def select_spark_batch_w7(spark, sf_dir):
    """The tree searches of each round spread over executors."""
    c, w = counts(spark, sf_dir, "w7")
    family = family_of(c, w, "w7")
    return one_row(spark, **select_row(spark, sf_dir, "w7", "greedy", batch=sel.spark_batch(spark, family, w.k, "greedy", "refined", [(c.total, c.path(0, 0, i)[1]) for i in range(w.k)]))).drop("seconds")


# ---- cover baseline

query(
    "cover_start_w6",
    f"WITH {ct('w6')}, s AS (SELECT i, sum(n * {bit('i')}) AS u FROM ct, (SELECT unnest(range(31)) AS i) GROUP BY i), t AS (SELECT u, sum(u) OVER () AS o FROM s WHERE u > 0) "
    "SELECT max(o)::BIGINT AS ones, round(sum(-u * log2(u / o)), 4) AS data_bits, round(sum(-2 * log2(u / o)), 4) AS table_bits, round(sum(-(u + 2) * log2(u / o)), 4) AS start_bits FROM t",
)(lambda s, d: cover_start(WORKLOADS["w6"].compact(s, d), 31))


@query(
    "cover_usage_w9",
    f"WITH {ct('w9')}, a AS (SELECT m, n, m & 1536 = 1536 AS h FROM ct), b AS (SELECT n, h, m & CASE WHEN h THEN ~1536::BIGINT ELSE -1 END AS r FROM a), c AS (SELECT n, h, r & 192 = 192 AS g, CASE WHEN r & 192 = 192 THEN r & ~192::BIGINT ELSE r END AS q FROM b) "
    "SELECT 1536::BIGINT AS mask, sum(n)::BIGINT AS usage FROM c WHERE h HAVING count(*) > 0 UNION ALL SELECT 192, sum(n)::BIGINT FROM c WHERE g HAVING count(*) > 0 UNION ALL SELECT (1::BIGINT << i), sum(n)::BIGINT FROM c, (SELECT unnest(range(11)) AS i) WHERE (q >> i) & 1 = 1 GROUP BY i",
)
def cover_usage_w9(spark, sf_dir):
    """Usages of a given table of two pairs and the singletons."""
    return cover_usage(WORKLOADS["w9"].compact(spark, sf_dir), [1536, 192], 11)


COVER_SETS = 5000  # itemsets that the cover of report_greedy can take: its support is the lowest with no more of them


def cover_row(spark, sf_dir, name: str, family=None, prune: bool = False) -> dict:
    """All candidates are tried. family: a function of the counts and the number of items."""
    c, w = counts(spark, sf_dir, name)
    t = time.perf_counter()
    family = family(c, w.k) if family else family_of(c, w, name)
    v = cover_baseline(c, family, prune)
    return {"workload": name, "candidates": len(family) - 1, "minsup": min(family.values()), "tried": v.tried, "truncated": v.truncated, "start_bits": v.start_bits, "bits": v.bits, "ratio_pct": v.ratio(), "itemsets": v.n_sets(), "seconds": time.perf_counter() - t}


for _name in ("w6", "w7", "w9"):
    query(f"cover_summary_{_name}")(lambda s, d, n=_name: one_row(s, **cover_row(s, d, n)).drop("seconds", "minsup"))
query("cover_pruned_w9")(lambda s, d: one_row(s, **cover_row(s, d, "w9", prune=True)).drop("seconds", "minsup"))


# ---- classification

DOCS = Workload("docs", ("documents",), "SELECT doc_id, text, lang, n_chars FROM documents", "doc_id", DOC_ITEMS)
ORDERS = Workload("orders", ("orders",), WORKLOADS["w5"].source, "o_orderkey", ORDER_REST)
SIGNS = Workload("signs", ("embeddings",), WORKLOADS["w10"].source, "vec_id", WORKLOADS["w10"].items[:16])


def labelled(spark, sf_dir, w: Workload, label: DataFrame) -> tuple[DataFrame, DataFrame]:
    rows = w.packed(spark, sf_dir).join(label, "key")
    held = ap.split_bucket(F.col("key"))
    return rows.where(~held), rows.where(held)


def labels_of(spark, sf_dir, kind: str) -> tuple[Workload, DataFrame]:
    read = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")
    if kind == "lang":
        return DOCS, read("documents").select(F.col("doc_id").alias("key"), F.col("lang").alias("label"))
    if kind == "quality":
        return DOCS, read("labels").select(F.col("doc_id").alias("key"), F.col("quality").cast("string").alias("label"))
    if kind == "status":
        return ORDERS, read("orders").select(F.col("o_orderkey").alias("key"), F.col("o_orderstatus").alias("label"))
    return SIGNS, read("embeddings").select(F.col("vec_id").alias("key"), F.col("label").cast("string").alias("label"))


def classify_row(spark, sf_dir, kind: str, smoothing: str = "kt", prior: bool = False) -> DataFrame:
    w, label = labels_of(spark, sf_dir, kind)
    train, test = labelled(spark, sf_dir, w, label)
    models = ap.fit_class_models(train, w.names)
    got = ap.accuracy(ap.classify_by_code_length(test, models, smoothing, prior))
    return got.crossJoin(ap.majority_accuracy(train, test).select(F.col("accuracy").alias("majority")))


for _kind in ("lang", "quality", "status", "vectors"):
    query(f"classify_{_kind}")(lambda s, d, k=_kind: classify_row(s, d, k))
query("classify_quality_prior")(lambda s, d: classify_row(s, d, "quality", prior=True))


@query("confusion_lang")
def confusion_lang(spark, sf_dir):
    w, label = labels_of(spark, sf_dir, "lang")
    train, test = labelled(spark, sf_dir, w, label)
    return ap.confusion(ap.classify_by_code_length(test, ap.fit_class_models(train, w.names)))


def _status_sql(end: str = "SELECT count(*) AS n_rows, sum((label = guess)::INT)::BIGINT AS n_right, round(avg((label = guess)::INT), 6) AS accuracy FROM g", prior: bool = False) -> str:
    p = ORDERS.packed_sql()
    k = ORDERS.k
    extra = "- log2(max(c.n) / (SELECT count(*) FROM p WHERE NOT held))" if prior else ""
    return (
        f"WITH p AS (SELECT a.key, a.m, o_orderstatus AS label, substr(md5('split-' || a.key), 1, 2) < '1a' AS held FROM ({p}) a JOIN orders ON o_orderkey = a.key), i AS (SELECT unnest(range({k})) AS i), "
        f"c AS MATERIALIZED (SELECT label, i, count(*) AS n, sum({bit('i')}) AS n1 FROM p, i WHERE NOT held GROUP BY ALL), "
        f"b AS (SELECT key, p.label, c.label AS guess, sum(-log2((CASE WHEN {bit('i')} = 1 THEN n1 ELSE n - n1 END + 1.0) / (n + 2.0))) {extra} AS bits FROM p, c WHERE held GROUP BY ALL), "
        f"g AS (SELECT key, label, guess FROM b QUALIFY row_number() OVER (PARTITION BY key ORDER BY bits, guess) = 1) {end}"
    )


def told_status(spark, sf_dir, prior: bool = False) -> DataFrame:
    """Held-out orders with the status told by single-leaf class models, Laplace-smoothed."""
    w, label = labels_of(spark, sf_dir, "status")
    train, test = labelled(spark, sf_dir, w, label)
    models = ap.fit_class_models(train, w.names, fit=lambda c: fixed_trees_model(c, w.names, [LEAF] * w.k))
    return ap.classify_by_code_length(test, models, "laplace", prior)


_RIGHT = {"rows": "n_rows", "right": "n_right"}
query("classify_independent_status", _status_sql())(lambda s, d: ap.accuracy(told_status(s, d)).withColumnsRenamed(_RIGHT))
query("classify_independent_status_prior", _status_sql(prior=True))(lambda s, d: ap.accuracy(told_status(s, d, True)).withColumnsRenamed(_RIGHT))


@query("confusion_independent_status", _status_sql("SELECT label, guess AS pred, count(*) AS n FROM g GROUP BY ALL"))
def confusion_independent_status(spark, sf_dir):
    """The confusion table, one row per cell that occurs."""
    wide = ap.confusion(told_status(spark, sf_dir))
    return wide.unpivot("label", [c for c in wide.columns if c != "label"], "pred", "n").where("n > 0")


@query(
    "majority_status",
    _status_sql("SELECT count(*) AS n_rows, sum((label = top)::INT)::BIGINT AS n_right, round(avg((label = top)::INT), 6) AS accuracy FROM p, (SELECT label AS top FROM p WHERE NOT held GROUP BY label ORDER BY count(*) DESC, label LIMIT 1) WHERE held"),
)
def majority_status(spark, sf_dir):
    w, label = labels_of(spark, sf_dir, "status")
    return ap.majority_accuracy(*labelled(spark, sf_dir, w, label)).withColumnsRenamed(_RIGHT)


# ---- reports


def _report(spark, rows: list[dict]) -> DataFrame:
    kinds = {int: "long", float: "double", str: "string", bool: "boolean"}
    return spark.createDataFrame([tuple(r.values()) for r in rows], ", ".join(f"{k} {kinds[type(v)]}" for k, v in rows[0].items()))


def greedy_report(spark, sf_dir, names) -> DataFrame:
    """Growth and cover baseline side by side, one row per workload. The cover's bits count only ones; its candidates are
    all itemsets at the lowest support with at most COVER_SETS of them, cover_minsup."""
    rows = []
    for n in names:
        with made_once():
            g, c = grow_row(spark, sf_dir, n), cover_row(spark, sf_dir, n, lambda c, k: it.mine_lowest(c, k, COVER_SETS))
        rows.append({k: v for k, v in g.items() if k not in ("seconds", "scans")} | {"cover_sets": c["itemsets"], "cover_bits": c["bits"], "cover_ratio_pct": c["ratio_pct"], "cover_truncated": c["truncated"], "cover_candidates": c["candidates"], "cover_minsup": c["minsup"]})
    return _report(spark, rows)


@query("report_greedy")
def report_greedy(spark, sf_dir):
    return greedy_report(spark, sf_dir, ("w4", "w5", "w6", "w7", "w8", "w9"))


query("report_greedy_unstructured")(lambda s, d: greedy_report(s, d, ("w3", "w10")))  # items that hardly depend on each other


@query("report_selection")
def report_selection(spark, sf_dir):
    """Both selection searches and the cover baseline over the same candidates."""
    rows = []
    for n in ("w3", "w4", "w5", "w6", "w7", "w8", "w9", "w10"):
        with made_once():
            e, g, c = select_row(spark, sf_dir, n, "exhaustive"), select_row(spark, sf_dir, n, "greedy"), cover_row(spark, sf_dir, n)
        rows.append({"workload": n, "candidates": e["candidates"], "exhaustive_bits": e["bits"], "exhaustive_pct": e["ratio_pct"], "exhaustive_sets": e["itemsets"], "greedy_bits": g["bits"], "greedy_pct": g["ratio_pct"], "greedy_sets": g["itemsets"], "cover_bits": c["bits"], "cover_sets": c["itemsets"]})
    return _report(spark, rows)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Growth on the order items: itemsets with names and supports."""
    m, _ = grown(spark, sf_dir, "w5")
    sets = m.itemsets_table(spark)
    return sets.join(_sets_with_supports(spark, sf_dir, "w5", m), "mask").select("mask", "names", "size", "supp")

