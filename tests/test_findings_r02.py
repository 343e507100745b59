"""Small data on which the findings of round 2 show."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from codetrees.operators.apply import RowScorer, symbol_bits
from codetrees.plans import registry
from codetrees.plans.counts import LocalCounts, bit_matrix, counts_of
from codetrees.plans.cover import Bits, total_bits
from codetrees.plans.greedy import grow_model, grow_naively
from codetrees.sources.workloads import WORKLOADS

QUERIES, SQL = registry.queries(), registry.oracle_sql()


def sql_on(sf_dir, name, *tables):
    con = duckdb.connect()
    for t in tables:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    cur = con.execute(SQL[name])
    return [d[0] for d in cur.description], cur.fetchall()


@pytest.mark.parametrize("rows, some", [(128, 1), (128, 3), (400_000, 1), (400_000, 13)])
def test_ratios_between_two_roundings(spark, same, tmp_path, rows, some):
    """Shares that end in a 5 after the sixth digit, exactly or but for the double's own error."""
    duckdb.execute(f"COPY (SELECT i AS p_partkey, CASE WHEN i < {some} THEN 'PROMO' ELSE 'LARGE' END AS p_type, 7::INT AS p_size, 900.0::DOUBLE AS p_retailprice FROM range({rows}) r(i)) TO '{tmp_path}/part.parquet' (FORMAT parquet)")
    same(QUERIES["o44_exact_ratio"](spark, str(tmp_path)), sql_on(tmp_path, "o44_exact_ratio", "part"))


MOVED = ["criteria_table", "leaf_sets_literal", "nml_table", "o20_item_pairs", "o48_pandas_udf", "o4_generator", "o50_table_function", "o52_sql_surface", "o54_plan"]


@pytest.mark.parametrize("name", MOVED)
def test_queries_read_tables_by_tasks(spark, sf_dir, name):
    """Input rows of all tasks that ran for the query."""

    def rows_read():
        found = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None)
        return {(found.apply(i).stageId(), found.apply(i).attemptId()): found.apply(i).inputRecords() for i in range(found.size())}

    before = rows_read()
    QUERIES[name](spark, sf_dir).collect()
    assert sum(n for stage, n in rows_read().items() if stage not in before) >= 15_000


def test_plan_table_shows_the_plan_that_ran(spark):
    from codetrees.sources.tables import plan_table

    got = {r["operator"]: r["n"] for r in plan_table(spark.range(100).groupBy((F.col("id") % 3).alias("x")).count()).collect()}
    assert got["HashAggregate"] == 2 and got["Exchange"] == 1 and "AdaptiveSparkPlan" not in got and "ShuffleQueryStage" not in got


def test_compact_rows_are_made_once_and_counted_in_few_waves(spark, sf_dir):
    made = spark.sparkContext.accumulator(0)
    w = WORKLOADS["w6"]

    def seen(batches):
        for b in batches:
            made.add(b.num_rows)
            yield b

    ct = w.compact(spark, sf_dir)
    rows = ct.count()
    far = counts_of(ct.mapInArrow(seen, "m long, n long"), w.k, local_cells=0)
    m = grow_model(far, w.names)
    assert made.value == rows and len(m.trace) > 100 and far.scans < len(m.trace) / 6


def test_local_counts_are_those_of_the_rows():
    rng = np.random.default_rng(1)
    words, n = rng.integers(0, 1 << 63, (3000, 2), dtype=np.uint64), rng.integers(1, 9, 3000)
    c = LocalCounts(words, n, 120)
    bits = bit_matrix(words, 120).astype(np.int64)
    for pos, neg, t in [(0, 0, 3), (0, 0, 3), (0, 0, 119), (1 << 70, 0, 3), (1 << 70, 1 << 2, 3), (1 << 70, 1 << 2, 5), (1 << 70, 1 << 2, 6), (3 << 118, 1 | 1 << 63, 9)]:
        at = np.array([all(r[i] == 1 for i in range(120) if pos >> i & 1) and all(r[i] == 0 for i in range(120) if neg >> i & 1) for r in bits])
        x, m = bits[at], n[at]
        got = c.path(pos, neg, t)
        assert got[:2] == (m.sum(), (m * x[:, t]).sum()) and (got[2] == m @ x).all() and (got[3] == (m * x[:, t]) @ x).all()


def test_bits_of_a_change_are_those_of_the_whole():
    rng = np.random.default_rng(2)
    single = {i: float(x) for i, x in enumerate(rng.uniform(1, 9, 12))}
    usage = {1 << i: int(u) for i, u in enumerate(rng.integers(1, 900_000, 12))} | {3: 5, 12: 40_000}
    for change in ({}, {5: 7, 1: -7, 4: -7}, {3: -5, 1: 5, 2: 5}, {48: 900, 16: -usage[16], 32: -900}, {3: 1}, {5: usage[1] // 2, 1: -(usage[1] // 2), 4: -1}):
        made = usage | {m: usage.get(m, 0) + d for m, d in change.items()}
        assert Bits(usage, single).change(change) == pytest.approx(total_bits(made, single) - total_bits(usage, single), abs=1e-6)


def test_pairs_of_many_regions_come_out_once(spark, monkeypatch):
    """In the later rounds of the n-gram join a pair comes out of one of its regions, not of each of them."""
    from fractions import Fraction

    from codetrees.llm import ngram_join as nj

    rows = []
    for f in range(6):  # texts around two centres that are just too far apart to link
        centre = [f"w{f}_{i}" for i in range(400)]
        other = [f"z{f}_{i}" if i % 6 == 0 and i <= 60 else w for i, w in enumerate(centre)]
        for i in range(24):
            words = list(other if i % 3 == 0 else centre)
            words[100 + 10 * i] = f"y{f}_{i}"
            rows.append((100 * f + i, " ".join(words)))
    docs = spark.createDataFrame(rows, f"{nj.RID} long, text string").repartition(3)
    raw = {m: spark.sparkContext.accumulator(0) for m in nj.ROUNDS}
    found, plain, write = [], nj._pairs, nj.written

    def counted(t, mode):
        f, n = plain(t, mode), raw[mode]

        def run(batches):
            for b in f(batches):
                n.add(b.num_rows)
                yield b

        return run

    def kept(df, name):
        out = write(df, name)
        if name == "pairs":
            found.append(out.count())
        return out

    monkeypatch.setattr(nj, "_pairs", counted)
    monkeypatch.setattr(nj, "written", kept)
    comps, labels = nj.similarity_links(docs, Fraction(3, 4), 5)
    assert len(found) == 3 and found[2] > 100
    assert raw["all"].value <= 1.5 * sum(found[1:])
    groups = comps.join(labels.withColumnRenamed("node", "comp"), "comp", "left").select(F.coalesce("label", "comp")).distinct().count()
    assert groups == 12


def test_first_common_region_of_a_pair():
    """A pair comes out in one of the regions that both rows are in at least, and in one only if their homes tell."""
    from codetrees.llm import ngram_join as nj

    r = np.random.default_rng(3)
    regions = [np.sort(r.choice(400, int(r.integers(1, 60)), replace=False)) - 200 for _ in range(80)]
    homes = np.full((80, nj.HOMES), nj.NO_HOME)
    for i, g in enumerate(regions):
        homes[i, : min(len(g), nj.HOMES)] = g[: nj.HOMES]
    once = 0
    for i in range(80):
        for j in range(i):
            both = np.intersect1d(regions[i], regions[j])
            came = 0
            for g in both:
                b = nj.Blocks.__new__(nj.Blocks)
                b.homes, b.region = homes, np.full(80, g)
                came += int(b._at_home(np.array([i]), np.array([j]))[0])
            told = len(np.intersect1d(regions[i][: nj.HOMES], regions[j][: nj.HOMES]))
            assert came == (1 if told else len(both))
            once += bool(told)
    assert once > 100


def test_tables_written_return_native_memory(spark, monkeypatch):
    """The driver's JVM is asked to return freed memory whenever a table is written, and can be."""
    from codetrees.llm import common

    assert common.trimmed(spark)
    asked, trim = [], common.trimmed
    monkeypatch.setattr(common, "trimmed", lambda s: asked.append(trim(s)))
    out = common.written(spark.range(3), "three")
    assert out.count() == 3 and asked == [True]
    common.dropped(out)


def test_growth_counts_the_smaller_part_of_a_split_only(monkeypatch):
    """On the driver: rows summed by growth, and leaves of every kind of multiplicity; the trees are those of the definition."""
    rng = np.random.default_rng(4)
    base = rng.random((3000, 1)) < 0.5
    x = (rng.random((3000, 9)) < 0.1) ^ base
    u, n = np.unique((x.astype(np.int64) << np.arange(9)).sum(1), return_counts=True)
    for times in (1, 2):
        c = LocalCounts(u.view(np.uint64).reshape(-1, 1), times * n, 9)
        seen, plain = [], c._ones
        monkeypatch.setattr(c, "_ones", lambda rows, seen=seen, plain=plain: seen.append(len(rows)) or plain(rows))
        m = grow_model(c, list("abcdefghi"))
        assert len(m.trace) > 5 and sum(seen) <= len(u) / 2 * len(m.trace)
        assert m.trace == grow_naively(LocalCounts(u.view(np.uint64).reshape(-1, 1), times * n, 9), list("abcdefghi")).trace


@pytest.mark.parametrize("k, times", [(3, 1), (9, 1), (120, 1), (120, 7)])
def test_parts_of_a_leaf_are_those_of_its_path(k, times):
    rng = np.random.default_rng(5)
    words = rng.integers(0, 1 << 63, (1500, -(-k // 63)), dtype=np.uint64)
    n = np.where(rng.random(1500) < 0.1, rng.integers(1, 9, 1500), times)
    c = LocalCounts(words, n, k)
    t, a, b = 1, 0, k - 1
    pos = neg = 0
    leaf = c.root(t)
    for item, side in ((a, 1), (b, 0)):
        got = c.split(leaf, t, item, pos, neg, [True, True])
        for part, p, q in ((got[0], pos | 1 << item, neg), (got[1], pos, neg | 1 << item)):
            want = LocalCounts(words, n, k).path(p, q, t)
            assert part[:2] == want[:2] and (part.nj == want[2]).all() and (part.n1j == want[3]).all()
        leaf, pos, neg = got[1 - side], pos | side << item, neg | (1 - side) << item
    assert c.split(leaf, t, 2 if k > 3 else 0, pos, neg, [False, False]) == [None, None]


def test_rows_are_scored_by_walking_down(monkeypatch):
    """Leaves are listed once for the whole model, and a row's bits are those of the leaves it reaches."""
    rng = np.random.default_rng(6)
    x = (rng.random((2000, 30)) < 0.15) ^ (rng.random((2000, 1)) < 0.5)
    words = (x.astype(np.int64) << np.arange(30)).sum(1).view(np.uint64).reshape(-1, 1)
    m = grow_model(LocalCounts(words, np.ones(2000, np.int64), 30), [str(i) for i in range(30)])
    rows = list(m.leaf_rows())
    calls = []
    plain = type(m).leaf_rows
    monkeypatch.setattr(type(m), "leaf_rows", lambda self: calls.append(1) or plain(self))
    s = RowScorer(m)
    assert len(calls) <= 1
    want, tally, place = np.zeros(2000), [], {}
    for t, pos, neg, n, n1 in rows:
        at = x[:, sorted(pos)].all(1) & ~x[:, sorted(neg)].any(1)
        want += at * np.where(x[:, t], symbol_bits(n, n1), symbol_bits(n, n - n1))
        leaf = place[t] = place.get(t, -1) + 1
        tally.append((t, leaf, n, n1)) if n else None
    assert s.bits(x) == pytest.approx(want) and [tuple(r) for r in s.tally(x, np.ones(2000, np.int64)).tolist()] == tally
    assert (s.restore(s.residuals(x)) == x).all()


def test_texts_are_taken_apart_twice_for_classes(spark, sf_dir):
    """Once for the vocabulary, once for the stored rows that training and hold-out share."""
    from codetrees.plans import wide_queries as wq

    train, test, _ = wq._labelled(spark, sf_dir)
    for rows in (train, test):
        plan = rows._jdf.queryExecution().optimizedPlan().toString()
        assert "regexp" not in plan and "w#" in plan
    assert train.count() + test.count() == spark.read.parquet(f"{sf_dir}/documents.parquet").where("lang IS NOT NULL").count()


@pytest.mark.parametrize("texts", [["b a a B c", "a, b-x", None, "c c", ""], [None, ""]])
def test_items_of_texts_are_looked_up_once(spark, tmp_path, texts):
    """One look-up of each word in the vocabulary, without a set of all words of a text before it."""
    from codetrees.sources.tables import wide_rows

    spark.createDataFrame([(i, "en", t) for i, t in enumerate(texts)], "doc_id long, lang string, text string").write.parquet(f"{tmp_path}/documents.parquet")
    rows, names = wide_rows(spark, str(tmp_path), 3, 2)
    assert names == (["a", "b", "c"] if texts[0] else [])
    assert "array_distinct" not in rows._jdf.queryExecution().optimizedPlan().toString()
    want = [[3, 1], [3, 0], [0, 0], [0, 1], [0, 0]] if names else [[], []]
    assert [r["w"] for r in rows.orderBy("key").collect()] == want
