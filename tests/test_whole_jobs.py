"""That registered queries do their whole job: no candidates, lengths or splits left out."""

import pytest

from codetrees.operators import itemsets as it
from codetrees.plans import core_queries as core
from codetrees.plans import registry
from codetrees.plans.counts import SparkCounts, counts_of
from codetrees.plans.cover import cover_baseline
from codetrees.plans.greedy import grow_model
from codetrees.sources.tables import wide_items
from codetrees.sources.workloads import WORKLOADS
from tests.test_search import counts_from, noise


def test_cover_queries_try_every_candidate(spark, sf_dir, monkeypatch):
    seen = []

    def cover(counts, family, prune=False, max_candidates=None):
        seen.append(max_candidates)
        return cover_baseline(counts, {m: s for m, s in family.items() if m.bit_count() < 2}, prune)

    monkeypatch.setattr(core, "cover_baseline", cover)
    monkeypatch.setattr(core, "grow_row", lambda s, d, n: {"workload": n})
    rows = core.report_greedy(spark, sf_dir).collect()
    core.Q["cover_summary_w6"](spark, sf_dir)
    assert seen == [None] * 7
    assert all(r["cover_candidates"] <= core.COVER_SETS for r in rows)


def test_lowest_support_of_so_many_sets():
    c = counts_from(noise())
    whole = it.mine_frequent(c, 5, 1)
    for most in (3, 8, 20, 31):
        got = it.mine_lowest(c, 5, most)
        least = min(got.values())
        below = max((s for s in whole.values() if s < least), default=None)
        assert got == {m: s for m, s in whole.items() if s >= least} and len(got) - 1 <= most
        assert below is None or sum(s >= below for s in whole.values()) - 1 > most


def test_families_have_no_limit_of_length(spark, sf_dir):
    for name, longest in (("w5", 9), ("w9", 6)):
        c, w = core.counts(spark, sf_dir, name)
        got = core.family_of(c, w, name)
        assert max(m.bit_count() for m in got) == longest
        assert got == it.mine_frequent(c, w.k, core._pct(c.total, core.FAMILIES[name]))


def test_wide_growth_goes_on_until_no_split_saves(spark, sf_dir):
    r = registry.queries()["w12_wide_stats"](spark, sf_dir).first()
    ct, names = wide_items(spark, sf_dir)
    m = grow_model(counts_of(ct, len(names)), names)
    assert r["splits"] == len(m.trace) > 60 and r["bits"] == m.cost()


@pytest.mark.parametrize("prune", [False, True])
def test_cover_by_spark_is_the_local_cover(spark, sf_dir, prune):
    w = WORKLOADS["w9"]
    ct = w.compact(spark, sf_dir)
    local, far = counts_of(ct, w.k), counts_of(ct, w.k, local_cells=0)
    assert isinstance(far, SparkCounts)
    family = it.mine_frequent(local, w.k, 300)
    a, b = cover_baseline(local, family, prune), cover_baseline(far, family, prune)
    assert a.table == b.table and len(a.table) > 3 and a.usage == b.usage
    assert (a.start_bits, a.bits) == pytest.approx((b.start_bits, b.bits)) and a.tried == b.tried


def test_low_entropy_sets_by_spark_are_the_local_ones(spark, sf_dir):
    w = WORKLOADS["w9"]
    ct = w.compact(spark, sf_dir)
    a, b = (it.mine_low_entropy(counts_of(ct, w.k, local_cells=n), w.k, 2.0, 3) for n in (10**6, 0))
    assert len(a) > w.k and a == pytest.approx(b)


def test_containment_join_without_broadcast(spark):
    """Many sets are joined by their lowest items, with the results of the broadcast join."""
    from codetrees.operators.relational import contains_join

    rows = spark.createDataFrame([(i, (i * 37) % 128) for i in range(60)] + [(99, (1 << 62) | 5)], "key long, m long")
    sets = spark.createDataFrame([(m,) for m in (0, 1, 2, 3, 5, 64, 65, 96, 1 << 62, (1 << 62) | 4)], "mask long")
    few, many = (sorted(map(tuple, contains_join(rows, sets, limit).select("key", "m", "mask").collect())) for limit in (100, 0))
    assert few == many and any(mask == 0 for _, _, mask in many)


def test_maximal_sets_close_to_the_family(spark):
    from codetrees.operators import itemsets as it

    family = spark.createDataFrame([(m,) for m in (1, 2, 4, 8, 3, 5, 6, 7)], "mask long")
    top = it.maximal_sets(family)
    assert {r["mask"] for r in top.collect()} == {7, 8}
    assert {r["mask"] for r in it.close_downward(top).collect()} == {r["mask"] for r in family.collect()}
