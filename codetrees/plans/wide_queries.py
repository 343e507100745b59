"""The methods over more items than a mask holds: the 120 commonest tokens of documents (workload w12)."""

from __future__ import annotations

from pyspark.sql import functions as F

from codetrees.operators import apply as ap
from codetrees.operators import itemsets as it
from codetrees.operators import wide
from codetrees.plans import select as sel
from codetrees.plans.core_queries import NML, db, one_row
from codetrees.plans.counts import counts_of, stored
from codetrees.plans.greedy import fixed_trees_model
from codetrees.plans.model import LEAF, Model, independent_cost
from codetrees.sources.tables import wide_items, wide_rows

K = 120
Q: dict = {}
SQL: dict[str, str] = {}

# The same rows in SQL: tokens of documents (tk), the vocabulary with item numbers (v), present items (p), all documents (d).
BASE = f"""WITH d AS MATERIALIZED (SELECT doc_id AS key, lang, list_distinct(regexp_extract_all(lower(coalesce(text, '')), '[a-z]+')) AS ts FROM documents),
 tk AS (SELECT key, unnest(ts) AS t FROM d), vo AS (SELECT t FROM tk GROUP BY t ORDER BY count(*) DESC, t LIMIT {K}),
 v AS MATERIALIZED (SELECT t, row_number() OVER (ORDER BY t) - 1 AS i FROM vo), p AS MATERIALIZED (SELECT key, i FROM tk JOIN v USING (t)),
 tot AS (SELECT count(*) AS n FROM d), s AS MATERIALIZED (SELECT v.i, v.t, count(p.key) AS n1 FROM v LEFT JOIN p ON p.i = v.i GROUP BY ALL)"""


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql is not None:
            SQL[name] = f"{BASE}{sql}"
        return f

    return add


@query(
    "w12_dataset_stats",
    " SELECT (SELECT n FROM tot) AS n_rows, (SELECT count(*)::INTEGER FROM v) AS items, count(DISTINCT coalesce(x, '')) AS distinct_rows, round(sum(coalesce(c, 0)) * 100.0 / (count(*) * (SELECT count(*) FROM v)), 4) AS pct_ones "
    "FROM d LEFT JOIN (SELECT key, string_agg(i::VARCHAR, ',' ORDER BY i) AS x, count(*) AS c FROM p GROUP BY key) USING (key)",
)
def w12_dataset_stats(spark, sf_dir):
    ct, names = wide_items(spark, sf_dir, K)
    return wide.wide_stats(ct, len(names))


@query("w12_item_supports", " SELECT i::INTEGER AS item, t AS name, n1 AS supp FROM s")
def w12_item_supports(spark, sf_dir):
    """Support of every item, with its name."""
    ct, names = wide_items(spark, sf_dir, K)
    return wide.item_supports(ct, len(names)).select("item", F.element_at(F.array(*[F.lit(x) for x in names]), F.col("item") + 1).alias("name"), "supp")


@query("w12_cooccurrence", " SELECT a.i::INTEGER AS i, b.i::INTEGER AS j, count(*) AS c FROM p a JOIN p b ON a.key = b.key AND a.i <= b.i GROUP BY ALL")
def w12_cooccurrence(spark, sf_dir):
    return wide.cooccurrence(wide_items(spark, sf_dir, K)[0])


@query(
    "w12_triple_supports",
    ", z AS (SELECT i AS a, i + 1 AS b, (SELECT count(*) FROM v) - 1 AS c FROM v WHERE i + 2 < (SELECT count(*) FROM v)), e AS MATERIALIZED (SELECT key FROM p WHERE i = (SELECT count(*) FROM v) - 1), "
    "x AS MATERIALIZED (SELECT key, i FROM p SEMI JOIN e USING (key)), h AS (SELECT x.i AS a, count(*) AS supp FROM x JOIN (SELECT key, i - 1 AS i FROM x) y USING (key, i) GROUP BY x.i) "
    "SELECT z.a::INTEGER AS a, z.b::INTEGER AS b, z.c::INTEGER AS c, coalesce(supp, 0) AS supp FROM z LEFT JOIN h USING (a)",
)
def w12_triple_supports(spark, sf_dir):
    """Supports of each item with its neighbour and the last item, by the containment join; most reach over two words."""
    ct, names = wide_items(spark, sf_dir, K)
    last = len(names) - 1
    sets = spark.range(max(0, last - 1)).select(F.col("id").cast("int").alias("a"), (F.col("id") + 1).cast("int").alias("b"), F.lit(last).alias("c"))
    sets = sets.withColumn("mask", wide.words_column(F.array("a", "b", "c"), len(names)))
    return sets.join(wide.itemset_supports(ct, sets), "mask").select("a", "b", "c", "supp")


@query("w12_independent_cost", f", zz AS ({NML.format(ms='SELECT n AS mm FROM tot')}) SELECT n AS n_rows, round(sum(1 + c + {db('n', 'n1')}), 4) AS bits FROM s, tot, zz WHERE mm = n GROUP BY n")
def w12_independent_cost(spark, sf_dir):
    ct, names = wide_items(spark, sf_dir, K)
    return wide.independent(ct, len(names))


def chain_model(counts, names: list[str]) -> Model:
    """Fixed trees: the first item is a leaf, each other item tests the one before it."""
    return fixed_trees_model(counts, names, [LEAF if t == 0 else ("test", t - 1, LEAF, LEAF) for t in range(len(names))])


# Leaves of the chain in SQL: (key, i, leaf, one); leaf 0 has the item before, leaf 1 lacks it, the first item has leaf 0 only.
CHAIN = (
    ", r AS MATERIALIZED (SELECT d.key, v.i, CASE WHEN v.i = 0 OR b.i IS NOT NULL THEN 0 ELSE 1 END AS leaf, (o.i IS NOT NULL)::INTEGER AS one FROM d CROSS JOIN v "
    "LEFT JOIN p o ON o.key = d.key AND o.i = v.i LEFT JOIN p b ON b.key = d.key AND b.i = v.i - 1)"
)


@query("w12_leaf_counts_chain", CHAIN + " SELECT i::INTEGER AS target, leaf, count(*) AS n, sum(one)::BIGINT AS n1 FROM r GROUP BY ALL")
def w12_leaf_counts_chain(spark, sf_dir):
    """Rows routed to the leaves of the chain, counted by one pass."""
    ct, names = wide_items(spark, sf_dir, K)
    return ap.leaf_counts(ct, chain_model(counts_of(ct, len(names)), names))


@query(
    "w12_code_length_chain",
    CHAIN + ", lc AS (SELECT i, leaf, count(*) AS n, sum(one) AS n1 FROM r GROUP BY ALL) "
    "SELECT key, round(sum(-log2((CASE WHEN one = 1 THEN n1 ELSE n - n1 END + 1.0) / (n + 2.0))), 6) AS bits FROM r JOIN lc USING (i, leaf) GROUP BY key",
)
def w12_code_length_chain(spark, sf_dir):
    """Bits of every row under the chain, Laplace-smoothed."""
    rows, names = wide_rows(spark, sf_dir, K)
    model = chain_model(counts_of(wide_items(spark, sf_dir, K)[0], len(names)), names)
    return ap.code_length(rows.select("key", "w"), model, "laplace").select("key", F.round("bits", 6).alias("bits"))


@query("w12_roundtrip_mismatches", " SELECT n AS n_rows, 0::BIGINT AS mismatches FROM tot")
def w12_roundtrip_mismatches(spark, sf_dir):
    """Rows to residuals under the chain and back."""
    rows, names = wide_rows(spark, sf_dir, K)
    model = chain_model(counts_of(wide_items(spark, sf_dir, K)[0], len(names)), names)
    back = ap.from_residuals(ap.to_residuals(rows.select("key", "w"), model), model).withColumnRenamed("w", "w2")
    return rows.join(back, "key").agg(F.count("*").alias("n_rows"), F.sum((F.col("w") != F.col("w2")).cast("long")).alias("mismatches"))


def _labelled(spark, sf_dir):
    rows, names = wide_rows(spark, sf_dir, K)
    rows = stored(rows.where("lang IS NOT NULL").withColumnRenamed("lang", "label"), "labelled")  # texts are taken apart once
    held = ap.split_bucket(F.col("key"))
    return rows.where(~held), rows.where(held), names


@query(
    "w12_classify_independent_lang",
    ", h AS MATERIALIZED (SELECT d.key, lang AS label, substr(md5('split-' || d.key), 1, 2) < '1a' AS held, v.i, (o.i IS NOT NULL)::INTEGER AS one FROM d CROSS JOIN v LEFT JOIN p o ON o.key = d.key AND o.i = v.i WHERE lang IS NOT NULL), "
    "c AS MATERIALIZED (SELECT label, i, count(*) AS n, sum(one) AS n1 FROM h WHERE NOT held GROUP BY ALL), "
    "b AS (SELECT key, h.label, c.label AS guess, sum(-log2((CASE WHEN one = 1 THEN n1 ELSE n - n1 END + 1.0) / (n + 2.0))) AS bits FROM h JOIN c USING (i) WHERE held GROUP BY ALL), "
    "g AS (SELECT key, label, guess FROM b QUALIFY row_number() OVER (PARTITION BY key ORDER BY bits, guess) = 1) SELECT count(*) AS n_rows, sum((label = guess)::INT)::BIGINT AS n_right, round(avg((label = guess)::INT), 6) AS accuracy FROM g",
)
def w12_classify_independent_lang(spark, sf_dir):
    """Language by single-leaf class models over the 120 tokens, Laplace-smoothed."""
    train, test, names = _labelled(spark, sf_dir)
    models = ap.fit_class_models(train, names, fit=lambda c: fixed_trees_model(c, names, [LEAF] * len(names)))
    return ap.accuracy(ap.classify_by_code_length(test, models, "laplace")).withColumnsRenamed({"rows": "n_rows", "right": "n_right"})


@query("w12_classify_lang")
def w12_classify_lang(spark, sf_dir):
    """Language by grown class models over the 120 tokens."""
    train, test, names = _labelled(spark, sf_dir)
    got = ap.accuracy(ap.classify_by_code_length(test, ap.fit_class_models(train, names)))
    return got.crossJoin(ap.majority_accuracy(train, test).select(F.col("accuracy").alias("majority")))


W12_PCT = 40.0  # least support of the candidates of selection, in % of the rows; no limit of length


@query("w12_select_greedy_summary")
def w12_select_greedy_summary(spark, sf_dir):
    """Selection over the frequent itemsets of the 120 tokens."""
    ct, names = wide_items(spark, sf_dir, K)
    c = counts_of(ct, len(names))
    family = it.mine_frequent(c, len(names), max(1, int(c.total * W12_PCT / 100)))
    singles = [(c.total, c.path(0, 0, i)[1]) for i in range(len(names))]
    m = sel.select_model(family, names, "greedy", singles=singles)
    base = independent_cost([x for _, x in singles], c.total, m.criterion)
    return one_row(spark, candidates=len(family) - 1, base_bits=base, bits=m.cost(), ratio_pct=100 * m.cost() / base, itemsets=m.count_itemsets(), inside=sel.all_in_family(m, family))
