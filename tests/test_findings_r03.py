"""Small data on which the findings of round 3 show."""

import tracemalloc

import numpy as np
import pytest

from codetrees.functions import codelen
from codetrees.operators import itemsets as it
from codetrees.plans import core_queries as core
from codetrees.plans.counts import LocalCounts
from codetrees.plans.cover import Walk, _usages
from codetrees.plans.greedy import grow_model
from codetrees.plans.model import count_between
from codetrees.sources.workloads import WORKLOADS


def test_itemsets_of_many_leaves_are_counted_in_little_memory():
    """Leaves whose itemsets are all those of other leaves take no part: as in trees of many splits."""
    rng = np.random.default_rng(1)
    words = np.unique(((rng.random((1000, 20)) < 0.15).astype(np.int64) << np.arange(20)).sum(1)).view(np.uint64).reshape(-1, 1)
    m = grow_model(LocalCounts(words, np.full(len(words), 20), 20), [str(i) for i in range(20)])
    tracemalloc.start()
    got = m.count_itemsets()
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(m.trace) > 1000 and peak < 16 << 20
    found = np.zeros(1 << 20, bool)
    for t, pos, neg in m.counts:
        found.reshape((2,) * 20)[tuple(1 if pos >> i & 1 else slice(None) if (neg | 1 << t) >> i & 1 else 0 for i in reversed(range(20)))] = True
    assert got == found[1:].sum()


@pytest.mark.parametrize("most", [0, 5, 40, 10**6])
def test_counts_of_itemsets_do_not_hang_on_what_is_remembered(most):
    rng = np.random.default_rng(most)
    spans = {(int(a & b), int(a | b)) for a, b in rng.integers(0, 1 << 11, (60, 2)).tolist()}
    assert count_between(spans, most) == sum(any(low & ~m == 0 and m & ~high == 0 for low, high in spans) for m in range(1 << 11))


def test_cost_walks_the_leaves_once(monkeypatch):
    rng = np.random.default_rng(2)
    x = (rng.random((3000, 12)) < 0.2) ^ (rng.random((3000, 1)) < 0.5)
    words = (x.astype(np.int64) << np.arange(12)).sum(1).view(np.uint64).reshape(-1, 1)
    m = grow_model(LocalCounts(words, np.full(3000, 7), 12), [str(i) for i in range(12)])
    apart = sum(m.tree_cost(t) for t in range(12))
    calls = []
    plain = type(m).leaf_rows
    monkeypatch.setattr(type(m), "leaf_rows", lambda self: calls.append(1) or plain(self))
    assert m.cost() == apart and len(calls) == 1 and len(m.trace) > 50
    assert apart == pytest.approx(sum(float(codelen.leaf_cost(n, n1)) for *_, n, n1 in plain(m)) + len(m.trace) * codelen.split_cost(12))


def test_masks_of_baskets_are_made_before_the_join(spark, sf_dir):
    """Once for each part, not for each line, and one number a line is dealt and aggregated, not one an item."""
    plan = WORKLOADS["w6"].compact(spark, sf_dir)._jdf.queryExecution().optimizedPlan().toString()
    above = plan[: plan.index("Join")]
    assert "bit_or" in above and "Brand#" not in above and "max(" not in plan and plan.count("Brand#25") == 1
    want = {(r["m"], r["n"]) for r in spark.sql(COMPACT, **{t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("lineitem", "part")}).collect()}
    assert {(r["m"], r["n"]) for r in WORKLOADS["w6"].compact(spark, sf_dir).collect()} == want


COMPACT = WORKLOADS["w6"].compact_sql("spark").replace("FROM lineitem JOIN part ON", "FROM {lineitem} lineitem JOIN {part} part ON")


@pytest.mark.parametrize("k, kind", [(9, np.uint32), (40, np.int64)])
def test_a_kept_candidate_changes_only_rows_it_fits_in(k, kind):
    """Usages that follow from one candidate to the next are those of the whole table walked anew."""
    rng = np.random.default_rng(k)
    rows = np.unique(((rng.random((500, 9)) < 0.45).astype(np.int64) << np.arange(9) * (k // 9)).sum(1))
    n = rng.integers(1, 9, len(rows))
    tries = sorted({int(a & b) for a in rows for b in rng.permutation(rows)[:40]}, key=lambda x: (-int(n[(rows & x) == x].sum()), -x.bit_count(), x))
    tries = [x for x in tries if x.bit_count() > 1]
    walk, table, supp = Walk(rows, n, k), [], {x: int(n[(rows & x) == x].sum()) for x in tries}
    assert walk.rows.dtype == kind and len(tries) > 100
    for i, x in enumerate(tries):
        after = sorted([*table, x], key=lambda m: (-m.bit_count(), -supp[m], m))
        a, b = _usages(rows, n, table, k), _usages(rows, n, after, k)
        assert walk.change(x) == {m: b.get(m, 0) - a.get(m, 0) for m in a.keys() | b.keys() if b.get(m, 0) != a.get(m, 0)}
        if i % 3:
            walk.join(x)
            table = after


def test_supports_share_rows_of_masks():
    rng = np.random.default_rng(4)
    words, n = rng.integers(0, 1 << 63, (400, 2), dtype=np.uint64), rng.integers(1, 9, 400)
    c = LocalCounts(words, n, 100)
    masks = [0, 1, 3, 5, 1 << 70, 1 << 70 | 1, 1 << 70 | 1 << 99, 1 << 70 | 1 << 99 | 2, 3]
    bits = [int(w[0]) | int(w[1]) << 63 for w in words.tolist()]
    assert c.supports(masks) == [sum(x for b, x in zip(bits, n.tolist(), strict=True) if b & m == m) for m in masks]


def test_reports_make_rows_and_candidates_once(spark, sf_dir, monkeypatch):
    made, mined = [], []
    counts_of, mine = core.counts_of, it.mine_frequent
    monkeypatch.setattr(core, "counts_of", lambda *a: made.append(1) or counts_of(*a))
    monkeypatch.setattr(it, "mine_frequent", lambda *a: mined.append(1) or mine(*a))
    apart = {n: (core.select_row(spark, sf_dir, n, "greedy"), core.cover_row(spark, sf_dir, n)) for n in ("w7", "w9")}
    assert len(made) == len(mined) == 4
    made.clear(), mined.clear()
    plain = core.WORKLOADS
    monkeypatch.setattr(core, "WORKLOADS", {n: plain["w9" if n != "w7" else n] for n in plain})
    monkeypatch.setattr(core, "FAMILIES", {n: 1.0 for n in core.FAMILIES})
    rows = {r["workload"]: r for r in core.report_selection(spark, sf_dir).collect()}
    assert len(made) == len(mined) == len(rows) == 8
    for n, (g, c) in apart.items():
        assert (rows[n]["greedy_bits"], rows[n]["cover_bits"], rows[n]["candidates"]) == (g["bits"], c["bits"], g["candidates"])
    made.clear()
    assert core.greedy_report(spark, sf_dir, ("w9",)).count() == 1 and len(made) == 1
    assert core._KEPT.get() is None
