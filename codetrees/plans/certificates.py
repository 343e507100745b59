"""Results of searches held against the rows, and summaries of given models, with the SQL of what they must give."""

from __future__ import annotations

from pyspark.sql import DataFrame

from codetrees.operators import apply as ap
from codetrees.plans import select as sel
from codetrees.plans.core_queries import LITERAL_COUNTS, NML, WORKLOADS, _report, counts, db, family_of, grown, literal_model, one_row
from codetrees.plans.cover import cover_baseline, cover_usage, total_bits
from codetrees.plans.model import LEAF, Model, independent_cost, items_of, leaves, load_model, mask_of, save_model, sources_of
from codetrees.sources.tables import scratch

Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def wrong_leaves(ct: DataFrame, model: Model) -> int:
    """Leaves whose counts differ from those of the rows routed to them."""
    got = {(r["target"], r["leaf"]): (r["n"], r["n1"]) for r in ap.leaf_counts(ct, model).collect()}
    want = {(t, i): model.counts[t, mask_of(p), mask_of(n)] for t, tree in enumerate(model.trees) for i, (p, n) in enumerate(leaves(tree))}
    return sum(1 for k in got.keys() | want.keys() if tuple(got.get(k, (0, 0))) != tuple(want.get(k, (0, 0))))


def order_violations(model: Model) -> int:
    """Tests of items that are not sent before the tested tree's target."""
    place = {i: p for p, i in enumerate(model.order())}
    return sum(1 for t, tree in enumerate(model.trees) for s in sources_of(tree) if place[s] >= place[t])


GROWN = ("w3", "w4", "w5", "w7", "w8", "w9", "w10")


def _values(rows: list[tuple], names: str) -> str:
    show = lambda x: f"'{x}'" if isinstance(x, str) else str(x).lower() if isinstance(x, bool) else f"{x}::BIGINT" if isinstance(x, int) else f"{x}::DOUBLE"
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(show(x) for x in r) + ')' for r in rows)}) v({names})"


@query("certify_growth", _values([(w, 0, 0, True, 0.0) for w in GROWN], "workload, wrong_leaves, order_violations, all_save, bits_off"))
def certify_growth(spark, sf_dir):
    """Grown models: leaf counts are those of the rows, no test comes too early, every split saved bits, and the total is
    the independent cost less what the splits saved."""
    rows = []
    for name in GROWN:
        m, c = grown(spark, sf_dir, name)
        base = independent_cost([c.path(0, 0, i)[1] for i in range(c.k)], c.total)
        off = m.cost() - (base - sum(t[4] for t in m.trace))
        rows.append({"workload": name, "wrong_leaves": wrong_leaves(WORKLOADS[name].compact(spark, sf_dir), m), "order_violations": order_violations(m), "all_save": all(t[4] > 0 for t in m.trace), "bits_off": abs(round(off, 3))})
    return _report(spark, rows)


SELECTED = ("w3", "w4", "w5", "w7", "w8", "w9")


@query("certify_selection", _values([(w, x, 0, 0, True, True) for w in SELECTED for x in ("exhaustive", "greedy")], "workload, search, wrong_leaves, order_violations, inside, saves"))
def certify_selection(spark, sf_dir):
    """Selected models: leaf counts found from supports are those of the rows, no test comes too early, all itemsets are
    candidates, and the model is not dearer than the independent one."""
    rows = []
    for name in SELECTED:
        c, w = counts(spark, sf_dir, name)
        family, ct = family_of(c, w, name), w.compact(spark, sf_dir)
        singles = [(c.total, c.path(0, 0, i)[1]) for i in range(w.k)]
        base = independent_cost([x for _, x in singles], c.total)
        for search in ("exhaustive", "greedy"):
            m = sel.select_model(family, w.names, search, singles=singles)
            rows.append({"workload": name, "search": search, "wrong_leaves": wrong_leaves(ct, m), "order_violations": order_violations(m), "inside": sel.all_in_family(m, family), "saves": m.cost() <= base + 1e-6})
    return _report(spark, rows)


COVERED = ("w5", "w7", "w9")


@query("certify_cover", _values([(w, 0, 0.0, True) for w in COVERED], "workload, wrong_usages, bits_off, saves"))
def certify_cover(spark, sf_dir):
    """Code tables found by the cover baseline: usages over the rows by a fold, and the bits that follow from them."""
    import numpy as np

    rows = []
    for name in COVERED:
        c, w = counts(spark, sf_dir, name)
        v = cover_baseline(c, family_of(c, w, name))
        ct = w.compact(spark, sf_dir)
        usage = {r["mask"]: r["usage"] for r in cover_usage(ct, v.table, w.k).collect()}
        ones = {items_of(r["mask"])[0]: r["usage"] for r in cover_usage(ct, [], w.k).collect()}
        single = {i: -np.log2(x / sum(ones.values())) for i, x in ones.items()}
        rows.append({"workload": name, "wrong_usages": sum(1 for k in usage.keys() | v.usage.keys() if usage.get(k) != v.usage.get(k)), "bits_off": abs(round(float(total_bits(usage, single) - v.bits), 3)), "saves": bool(v.bits <= v.start_bits)})
    return _report(spark, rows)


# ---- the literal model on w5

_LITERAL = (
    f"WITH {LITERAL_COUNTS}, b AS (SELECT i, sum(n)::BIGINT AS n, sum(n * ((m >> i) & 1))::BIGINT AS n1 FROM ct, (SELECT unnest(range(18)) AS i) GROUP BY i), "
    f"z AS MATERIALIZED ({NML.format(ms='SELECT n AS mm FROM lc UNION SELECT n FROM b')}), "
    f"x AS (SELECT sum(1 + c + {db('n', 'n1')}) + 4 * (1 + log2(18)) AS bits FROM lc JOIN z ON mm = n), y AS (SELECT sum(1 + c + {db('n', 'n1')}) AS base FROM b JOIN z ON mm = n)"
)


@query(
    "model_summary_literal_w5",
    f"{_LITERAL}, s AS (SELECT DISTINCT v AS mask FROM al, (SELECT unnest(range(1, 262144)) AS v) WHERE v & pos = pos AND v & ~(pos | neg | (1::BIGINT << target)) = 0) "
    "SELECT round(base, 4) AS base_bits, round(bits, 4) AS bits, round(100 * bits / base, 4) AS ratio_pct, 2::BIGINT AS trees, (SELECT count(*) FROM s) AS itemsets FROM x, y",
)
def model_summary_literal_w5(spark, sf_dir):
    """Bits, ratio, number of trees that test anything and number of itemsets of the literal trees."""
    m = literal_model(spark, sf_dir)
    base = independent_cost([r["n1"] for r in ap.leaf_counts(WORKLOADS["w5"].compact(spark, sf_dir), _bare(m)).orderBy("target").collect()], m.total)
    return one_row(spark, base_bits=round(base, 4), bits=round(m.cost(), 4), ratio_pct=round(100 * m.cost() / base, 4), trees=len(m.signatures()), itemsets=m.count_itemsets())


def _bare(m: Model) -> Model:
    return Model(m.names, m.total, [LEAF] * m.k)


@query("o5_model_store_literal", f"{_LITERAL} SELECT round(bits, 4) AS bits, true AS same FROM x")
def o5_model_store_literal(spark, sf_dir):
    """The literal model saved and loaded."""
    m, path = literal_model(spark, sf_dir), scratch(spark, "model")
    save_model(m, spark, path, "literal")
    got = load_model(spark, path, "literal")
    return one_row(spark, bits=round(got.cost(), 4), same=got.trees == m.trees and got.counts == m.counts)


@query("tree_signatures_literal_w5", "SELECT 'status_F,status_O,status_P' AS items UNION ALL SELECT 'price_gt_100k,price_gt_200k,year_ge_1996'")
def tree_signatures_literal_w5(spark, sf_dir):
    return spark.createDataFrame([(",".join(x),) for x in literal_model(spark, sf_dir).signatures()], "items string")


@query("packed_by_literal_w5", "SELECT * FROM (VALUES ('status_O', 'status_F'), ('status_P', 'status_F'), ('price_gt_200k', 'price_gt_100k'), ('year_ge_1996', 'price_gt_100k')) v(item, used_by)")
def packed_by_literal_w5(spark, sf_dir):
    """Who tests each item, for the items that are tested."""
    m = literal_model(spark, sf_dir)
    return spark.createDataFrame([(n, ",".join(m.packed_by(n))) for n in m.names if m.packed_by(n)], "item string, used_by string")


@query(
    "tree_text_literal_w5",
    f"WITH {LITERAL_COUNTS}, s AS (SELECT CASE WHEN pos = 2 THEN 0 WHEN pos = 4 THEN 1 ELSE 2 END AS place, printf('P(status_F) = %.3f of %d', n1::DOUBLE / n, n) AS x FROM lc WHERE target = 0) "
    "SELECT 'status_F' AS target, 'status_O?' || chr(10) || '  yes' || chr(10) || '    ' || max(x) FILTER (place = 0) || chr(10) || '  no' || chr(10) || '    status_P?' || chr(10) || '      yes' || chr(10) || '        ' || max(x) FILTER (place = 1) "
    "|| chr(10) || '      no' || chr(10) || '        ' || max(x) FILTER (place = 2) AS tree FROM s",
)
def tree_text_literal_w5(spark, sf_dir):
    return spark.createDataFrame([("status_F", literal_model(spark, sf_dir).explain(0))], "target string, tree string")
