"""Binary data sets over the given tables: item catalogues as portable SQL, and the layouts built from them."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

WORD_BITS = 63

# The frozen token list of doc_tokens.
TOKENS = "en in the of on and to a is be as that er it re was for an with this es are by ou".split()
LANGS = ["en", "fr", "de", "es"]
TYPES = ["MEDIUM", "STANDARD", "LARGE", "PROMO", "SMALL", "ECONOMY"]
EVENTS = ["view", "signup", "purchase", "error", "click"]


@dataclass(frozen=True)
class Item:
    """An attribute: a name and a predicate. {tok:x} and {dim:i} stand for engine-specific spellings."""

    name: str
    expr: str

    def sql(self, engine: str) -> str:
        out = self.expr
        if engine == "spark":
            return out.replace("{tokens}", "regexp_extract_all(lower(text), '[a-z]+', 0)").replace("{has}", "array_contains").replace("{at}", "element_at")
        return out.replace("{tokens}", "regexp_extract_all(lower(text), '[a-z]+')").replace("{has}", "list_contains").replace("{at}", "list_extract")


@dataclass(frozen=True)
class Workload:
    """Rows of `source` (portable SQL over the tables), one transaction each, or one per group of `group` if given, where
    an item is present when any row of the group has it. joined: a table whose columns alone the items read, and the source
    with the masks m of its rows in place of these columns, so that masks are made before the join, once per row of it."""

    name: str
    tables: tuple[str, ...]
    source: str
    key: str
    items: tuple[Item, ...]
    group: tuple[str, ...] = field(default=())
    joined: tuple[str, str] = field(default=())

    @property
    def k(self) -> int:
        return len(self.items)

    @property
    def names(self) -> list[str]:
        return [i.name for i in self.items]

    def mask_sql(self, engine: str, grouped: bool = True) -> str:
        """grouped: the mask of the whole group, where there are groups, in place of each row's own."""
        flags = [f"coalesce({i.sql(engine)}, false)" for i in self.items]
        bit = [f"CASE WHEN {f} THEN {1 << i} ELSE 0 END" for i, f in enumerate(flags)]
        if self.group and grouped:
            bit = [f"max({b})" for b in bit]
        return "cast(" + " + ".join(bit) + " AS bigint)"

    def packed_sql(self, engine: str = "duckdb") -> str:
        """SQL for (key, m)."""
        if self.group:
            return f"SELECT {self.key} AS key, {self.mask_sql(engine)} AS m FROM ({self.source}) GROUP BY {', '.join(self.group)}"
        return f"SELECT {self.key} AS key, {self.mask_sql(engine)} AS m FROM ({self.source})"

    def compact_sql(self, engine: str = "duckdb") -> str:
        return f"SELECT m, count(*) AS n FROM ({self.packed_sql(engine)}) GROUP BY m"

    def packed(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """(key, m): rows as bit masks (K <= 63). Only the columns of the predicates are read."""
        if self.k > WORD_BITS:
            raise ValueError("more than 63 items: use sources.layouts.pack_words")
        base = spark.sql(self.source, **{t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in self.tables}) if "{" in self.source else None
        mask = self.mask_sql("spark", False)
        if self.group and self.joined:
            table, source = self.joined
            base, mask = _sql(spark, sf_dir, self.tables, source, {table: f"*, {mask} AS m"}), "m"
        elif base is None:
            base = _sql(spark, sf_dir, self.tables, self.source)
        if self.group:
            key = F.first(F.expr(self.key)) if self.key not in self.group else F.max(F.expr(self.key))
            made = base.groupBy(*[F.expr(g) for g in self.group]).agg(key.alias("key"), F.bit_or(F.expr(mask)).alias("m"))
            return made.select("key", "m")
        return base.selectExpr(f"{self.key} AS key", f"{self.mask_sql('spark')} AS m")

    def compact(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """(m, n): distinct rows with counts; all costs are functions of these."""
        return self.packed(spark, sf_dir).groupBy("m").agg(F.count("*").alias("n"))

    def restricted(self, keep: list[str], name: str) -> Workload:
        """The same rows with some of the items only, in the order given."""
        by = {i.name: i for i in self.items}
        return Workload(name, self.tables, self.source, self.key, tuple(by[n] for n in keep), self.group, self.joined)


def _sql(spark: SparkSession, sf_dir: str, tables, text: str, columns: dict[str, str] | None = None) -> DataFrame:
    """Run SQL over the parquet tables without registering views of fixed names. columns: what to select of a table."""
    for t in tables:
        text = _replace_table(text, t)
    read = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in tables}
    for t, some in (columns or {}).items():
        read[t] = spark.sql(f"SELECT {some} FROM {{t}}", t=read[t])
    return spark.sql(text, **{f"t_{t}": x for t, x in read.items()})


def _replace_table(text: str, table: str) -> str:
    import re

    return re.sub(rf"\b(FROM|JOIN)\s+{table}\b", rf"\1 {{t_{table}}} {table}", text)


def sql_over(spark: SparkSession, sf_dir: str, tables, text: str) -> DataFrame:
    """Spark SQL text over the named parquet tables."""
    return _sql(spark, sf_dir, tables, text)


def _toy(chain: bool) -> tuple[Item, ...]:
    byte = lambda i: f"substr(md5(concat(o_orderkey, '-', {i})), 1, 2)"
    if not chain:
        return tuple(Item(f"a{i}", f"{byte(i)} < '80'") for i in range(1, 11))
    flips = [f"CASE WHEN {byte(i)} < '{'80' if i == 1 else '1a'}' THEN 1 ELSE 0 END" for i in range(1, 11)]
    return tuple(Item(f"a{i}", f"({' + '.join(flips[:i])}) % 2 = 1") for i in range(1, 11))


def _items(*pairs) -> tuple[Item, ...]:
    return tuple(Item(n, e) for n, e in pairs)


_TOY = "SELECT o_orderkey FROM orders WHERE o_orderkey < 2000"
_TOY_ALL = "SELECT o_orderkey FROM orders"
_LINE = "SELECT l_orderkey, l_linenumber, l_quantity, l_discount, l_tax, l_linestatus, l_returnflag, l_extendedprice, l_shipdate FROM lineitem"

STATUS = _items(*[(f"status_{s}", f"o_orderstatus = '{s}'") for s in "FOP"])
ORDER_REST = _items(
    *[(f"prio_{i}", f"substr(o_orderpriority, 1, 1) = '{i}'") for i in range(1, 6)],
    *[(f"price_gt_{p}k", f"o_totalprice > {p}000") for p in (100, 200, 300, 400)],
    *[(f"year_ge_{y}", f"year(o_orderdate) >= {y}") for y in range(1996, 2002)],
)
DOC_ITEMS = _items(*[(f"tok_{t}", f"{{has}}({{tokens}}, '{t}')") for t in TOKENS])
LANG_ITEMS = _items(*[(f"lang_{x}", f"lang = '{x}'") for x in LANGS])

WORKLOADS: dict[str, Workload] = {
    w.name: w
    for w in [
        Workload("w1", ("orders",), _TOY, "o_orderkey", _toy(False)),
        Workload("w2", ("orders",), _TOY, "o_orderkey", _toy(True)),
        Workload("w1_all", ("orders",), _TOY_ALL, "o_orderkey", _toy(False)),
        Workload("w2_all", ("orders",), _TOY_ALL, "o_orderkey", _toy(True)),
        Workload(
            "w3", ("lineitem",), _LINE, "l_orderkey",
            _items(("qty_gt_25", "l_quantity > 25"), ("disc_gt_5", "l_discount > 0.05"), ("tax_gt_4", "l_tax > 0.04"), ("status_o", "l_linestatus = 'O'"), ("flag_r", "l_returnflag = 'R'"), ("price_gt_50k", "l_extendedprice > 50000"), ("ship_ge_98_06", "l_shipdate >= '1998-06-01'"), ("line_gt_4", "l_linenumber > 4")),
        ),
        Workload(
            "w4", ("lineitem",), _LINE, "l_orderkey",
            _items(*[(f"flag_{x}", f"l_returnflag = '{x}'") for x in "ANR"], *[(f"status_{x}", f"l_linestatus = '{x}'") for x in "FO"], *[(f"line_{i}", f"l_linenumber = {i}") for i in range(1, 8)], *[(f"qty_gt_{q}", f"l_quantity > {q}") for q in (10, 20, 30, 40)], *[(f"disc_gt_{d}", f"l_discount > 0.0{d}1") for d in (2, 5, 8)]),
        ),
        Workload("w5", ("orders",), "SELECT o_orderkey, o_orderstatus, o_orderpriority, o_totalprice, o_orderdate FROM orders", "o_orderkey", STATUS + ORDER_REST),
        Workload(
            "w6", ("lineitem", "part"), "SELECT l_orderkey, p_type, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey", "l_orderkey",
            _items(*[(f"type_{t}", f"p_type = '{t}'") for t in TYPES], *[(f"brand_{b}", f"p_brand = 'Brand#{b}'") for b in range(1, 26)]), ("l_orderkey",),
            ("part", "SELECT l_orderkey, m FROM lineitem JOIN part ON l_partkey = p_partkey"),
        ),
        Workload(
            "w7", ("events",), "SELECT user_id, cast(ts AS date) AS day, event_type, value FROM events", "user_id",
            _items(*[(e, f"event_type = '{e}'") for e in EVENTS], *[(f"{e}_gt_100", f"event_type = '{e}' AND value > 100") for e in EVENTS]), ("user_id", "day"),
        ),
        Workload("w8", ("documents",), "SELECT doc_id, text, lang, n_chars FROM documents", "doc_id", DOC_ITEMS + LANG_ITEMS + _items(("long", "n_chars > 1000"))),
        Workload(
            "w9", ("part",), "SELECT p_partkey, p_type, p_size, p_retailprice FROM part", "p_partkey",
            _items(*[(f"type_{t}", f"p_type = '{t}'") for t in TYPES], *[(f"size_gt_{s}", f"p_size > {s}") for s in (10, 20, 30, 40)], ("price_gt_950", "p_retailprice > 950")),
        ),
        Workload("w10", ("embeddings",), "SELECT vec_id, embedding, label FROM embeddings", "vec_id", _items(*[(f"dim_{i}", f"{{at}}(embedding, {i}) > 0") for i in range(1, 17)], *[(f"label_{i}", f"label = {i}") for i in range(10)])),
    ]
}
