"""Queries of the surrounding operators, with SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from codetrees.functions import udfs
from codetrees.operators import relational as r
from codetrees.plans.core_queries import REACHED_SQL, ct, db, reached_leaves
from codetrees.sources import tables as src
from codetrees.sources.workloads import WORKLOADS, sql_over

Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def t(spark, sf_dir, name, *cols):
    return r.load(spark, sf_dir, name, list(cols) or None)


query("o1_scan", "SELECT o_orderkey, o_orderstatus FROM orders")(lambda s, d: t(s, d, "orders", "o_orderkey", "o_orderstatus"))
query("o2_basket_files", f"SELECT key, list_sort(list_filter(range(31), lambda i: (m >> i) & 1 = 1))::VARCHAR AS items FROM ({WORKLOADS['w6'].packed_sql()})")(
    lambda s, d: src.basket_roundtrip(WORKLOADS["w6"].packed(s, d), 31)
)
query("o3_formats", "SELECT f.f AS format, count(*) AS n_rows, round(sum(p_retailprice), 2) AS price, min(p_name) AS first_name FROM part, (SELECT unnest(['csv', 'json', 'orc', 'parquet']) AS f) f GROUP BY f.f")(lambda s, d: src.format_roundtrip(t(s, d, "part")))
query("o4_generator", "SELECT o_orderkey AS key, substr(md5('7-' || o_orderkey || '-1'), 1, 2) < '80' AS a1, substr(md5('7-' || o_orderkey || '-2'), 1, 2) < '80' AS a2 FROM orders")(
    lambda s, d: src.toy(t(s, d, "orders", "o_orderkey").withColumnRenamed("o_orderkey", "key"), 2, "independent", 7)
)
query("o5_model_store")(lambda s, d: src.model_roundtrip(s, d))
query("o6_project_items", "SELECT coalesce(l_quantity > 25, false) AS qty, coalesce(l_returnflag = 'R', false) AS returned, count(*) AS n FROM lineitem GROUP BY ALL")(
    lambda s, d: r.project_items(t(s, d, "lineitem", "l_quantity", "l_returnflag"), {"qty": "l_quantity > 25", "returned": "l_returnflag = 'R'"}).groupBy("qty", "returned").agg(F.count("*").alias("n"))
)
query("o7_one_hot", "SELECT o_orderkey, o_orderstatus = 'F' AS o_orderstatus_0, o_orderstatus = 'O' AS o_orderstatus_1 FROM orders")(lambda s, d: r.one_hot(t(s, d, "orders"), "o_orderstatus", ["F", "O"], ["o_orderkey"]))
query("o8_thresholds", "SELECT o_orderkey, o_totalprice > 100000 AS o_totalprice_gt_0, o_totalprice > 300000 AS o_totalprice_gt_1 FROM orders")(lambda s, d: r.threshold_items(t(s, d, "orders"), "o_totalprice", [100000, 300000], ["o_orderkey"]))
query("o8_equi_width", "SELECT CASE WHEN p_retailprice < 900 THEN 0 WHEN p_retailprice >= 1100 THEN 5 ELSE floor((p_retailprice - 900) / 50)::INT + 1 END AS bin, count(*) AS n FROM part GROUP BY 1")(
    lambda s, d: r.equi_width(t(s, d, "part", "p_retailprice"), "p_retailprice", 900, 1100, 4).groupBy(F.col("bin").cast("int").alias("bin")).agg(F.count("*").alias("n"))
)
query("o9_quantiles", "SELECT round(quantile_cont(o_totalprice, 0.25), 6) AS q0, round(quantile_cont(o_totalprice, 0.5), 6) AS q1, round(quantile_cont(o_totalprice, 0.75), 6) AS q2 FROM orders")(
    lambda s, d: r.quantile_cuts(t(s, d, "orders", "o_totalprice"), "o_totalprice", [0.25, 0.5, 0.75]).select(*[F.round(f"q{i}", 6).alias(f"q{i}") for i in range(3)])
)
query("o9_quantiles_approx")(lambda s, d: r.quantile_cuts(t(s, d, "orders", "o_totalprice"), "o_totalprice", [0.25, 0.5, 0.75], True))
query("o10_pack_unpack", f"SELECT key, (m & 1) <> 0 AS a, (m & 2) <> 0 AS b, (m & 4) <> 0 AS c FROM ({WORKLOADS['w5'].packed_sql()})")(lambda s, d: r.unpack(WORKLOADS["w5"].packed(s, d), ["a", "b", "c"], ["key"]))
query("o11_filters", "SELECT count(*) AS n FROM part WHERE p_name LIKE 'red%' OR p_size BETWEEN 10 AND 12 AND p_type IN ('PROMO', 'SMALL') OR regexp_matches(p_brand, '#2[0-3]$') AND p_size IS NOT NULL")(
    lambda s, d: t(s, d, "part", "p_name", "p_size", "p_type", "p_brand").where("p_name LIKE 'red%' OR p_size BETWEEN 10 AND 12 AND p_type IN ('PROMO', 'SMALL') OR p_brand RLIKE '#2[0-3]$' AND p_size IS NOT NULL").agg(F.count("*").alias("n"))
)


@query("o12_join_small", "SELECT r_name, o_orderstatus, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def o12(s, d):
    x = t(s, d, "orders", "o_custkey", "o_orderstatus").join(t(s, d, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    x = r.join_small(x, t(s, d, "nation", "n_nationkey", "n_regionkey"), F.col("c_nationkey") == F.col("n_nationkey"))
    x = r.join_small(x, t(s, d, "region", "r_regionkey", "r_name"), F.col("n_regionkey") == F.col("r_regionkey"))
    return x.groupBy("r_name", "o_orderstatus").agg(F.count("*").alias("n"))


for _hint in ("merge", "shuffle_hash"):
    query(f"o13_join_{_hint}", "SELECT o_orderstatus, l_returnflag, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL")(
        lambda s, d, h=_hint: r.join_large(t(s, d, "lineitem", "l_orderkey", "l_returnflag"), t(s, d, "orders", "o_orderkey", "o_orderstatus"), F.col("l_orderkey") == F.col("o_orderkey"), h).groupBy("o_orderstatus", "l_returnflag").agg(F.count("*").alias("n"))
    )
for _how, _sqlhow in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    query(f"o14_join_{_how}", f"SELECT quality, toxic, count(*) AS n FROM documents {_sqlhow} JOIN labels USING (doc_id) GROUP BY ALL")(
        lambda s, d, h=_how: t(s, d, "documents", "doc_id").join(t(s, d, "labels"), "doc_id", h).groupBy("quality", "toxic").agg(F.count("*").alias("n"))
    )
query("o15_semi", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")(lambda s, d: t(s, d, "documents", "doc_id").join(t(s, d, "labels", "doc_id"), "doc_id", "left_semi"))
query("o15_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")(lambda s, d: t(s, d, "documents", "doc_id").join(t(s, d, "labels", "doc_id"), "doc_id", "left_anti"))
query("o16_containment", f"WITH p AS ({WORKLOADS['w6'].packed_sql()}) SELECT mask::BIGINT AS mask, count(*) AS n FROM p, (VALUES (3), (65), (7)) v(mask) WHERE m & mask = mask GROUP BY mask")(
    lambda s, d: r.contains_join(WORKLOADS["w6"].packed(s, d), s.createDataFrame([(3,), (65,), (7,)], "mask long")).groupBy("mask").agg(F.count("*").alias("n"))
)
query("o17_range_join", "SELECT bin, count(*) AS n FROM lineitem JOIN (VALUES (0, 0, 20000), (1, 20000, 50000), (2, 50000, 1000000)) v(bin, lo, hi) ON l_extendedprice >= lo AND l_extendedprice < hi GROUP BY bin")(
    lambda s, d: r.bin_join(t(s, d, "lineitem", "l_extendedprice"), s.createDataFrame([(0, 0, 20000), (1, 20000, 50000), (2, 50000, 1000000)], "bin int, lo int, hi int"), "l_extendedprice").groupBy("bin").agg(F.count("*").alias("n"))
)
query(
    "o18_asof",
    "WITH c AS (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'click' GROUP BY ALL) SELECT p.event_id, c.event_id AS prev FROM events p ASOF LEFT JOIN c ON p.user_id = c.user_id AND p.ts >= c.ts WHERE p.event_type = 'purchase'",
)(
    lambda s, d: r.asof_prev(t(s, d, "events", "event_id", "user_id", "ts", "event_type").where("event_type = 'purchase'"), t(s, d, "events").where("event_type = 'click'").groupBy("user_id", "ts").agg(F.max("event_id").alias("click")), "user_id", "ts", "click").select("event_id", "prev")
)
query("o19_within", "SELECT a.event_id, b.event_id AS r_event_id FROM events a JOIN events b ON a.user_id = b.user_id AND abs(epoch(date_trunc('second', a.ts)) - epoch(date_trunc('second', b.ts))) <= 3600 WHERE a.event_type = 'purchase' AND b.event_type = 'click'")(
    lambda s, d: r.within(t(s, d, "events", "event_id", "user_id", "ts", "event_type").where("event_type = 'purchase'"), t(s, d, "events", "event_id", "user_id", "ts", "event_type").where("event_type = 'click'"), "user_id", "ts", 3600).select("event_id", "r_event_id")
)
query("o20_item_pairs", f"WITH {ct('w6')}, i AS (SELECT DISTINCT i FROM ct, (SELECT unnest(range(31)) AS i) WHERE (m >> i) & 1 = 1) SELECT a.i::INT AS i, b.i::INT AS j FROM i a, i b WHERE a.i < b.i")(
    lambda s, d: r.item_pairs(WORKLOADS["w6"].compact(s, d).select(F.explode_outer(F.expr("filter(sequence(0, 30), i -> (shiftright(m, i) & 1) = 1)")).alias("i")).where("i is not null"))
)
query("o21_hash_aggregate", "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity)::DOUBLE AS qty, round(avg(l_extendedprice), 6) AS price, min(l_discount) AS lo, max(l_discount) AS hi FROM lineitem GROUP BY ALL")(
    lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("double").alias("qty"), F.round(F.avg("l_extendedprice"), 6).alias("price"), F.min("l_discount").alias("lo"), F.max("l_discount").alias("hi"))
)
query("o22_baskets", "SELECT l_orderkey, array_to_string(list_sort(list_distinct(list(p_brand))), ',') AS items FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY l_orderkey")(
    lambda s, d: r.to_baskets(t(s, d, "lineitem", "l_orderkey", "l_partkey").join(t(s, d, "part", "p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")), "l_orderkey", "p_brand").select("l_orderkey", F.concat_ws(",", "items").alias("items"))
)
query("o23_presence", "SELECT user_id, bool_or(event_type = 'click') AS click, bool_or(value > 100) AS large, count(*) FILTER (event_type = 'click') AS n_click, count(*) FILTER (value > 100) AS n_large FROM events GROUP BY user_id")(
    lambda s, d: r.presence(t(s, d, "events"), ["user_id"], {"click": "event_type = 'click'", "large": "value > 100"})
)
query("o24_distinct", "SELECT count(DISTINCT p_brand) AS brands, count(DISTINCT (p_brand, p_type)) AS both FROM part".replace(" AS both", " AS brand_types"))(lambda s, d: t(s, d, "part").agg(F.countDistinct("p_brand").alias("brands"), F.countDistinct("p_brand", "p_type").alias("brand_types")))
query("o25_cube", "SELECT o_orderstatus, substr(o_orderpriority, 1, 1) AS prio, grouping(o_orderstatus, substr(o_orderpriority, 1, 1))::BIGINT AS gid, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, substr(o_orderpriority, 1, 1))")(
    lambda s, d: r.cells(t(s, d, "orders").select("o_orderstatus", F.substring("o_orderpriority", 1, 1).alias("prio")), ["o_orderstatus", "prio"], "cube")
)
query("o25_rollup", "SELECT o_orderstatus, substr(o_orderpriority, 1, 1) AS prio, grouping(o_orderstatus, substr(o_orderpriority, 1, 1))::BIGINT AS gid, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, substr(o_orderpriority, 1, 1))")(
    lambda s, d: r.cells(t(s, d, "orders").select("o_orderstatus", F.substring("o_orderpriority", 1, 1).alias("prio")), ["o_orderstatus", "prio"], "rollup")
)
query("o26_pivot", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM orders GROUP BY 1")(
    lambda s, d: t(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0)
)
query("o26_unpivot", "SELECT p_partkey, name, v FROM (SELECT p_partkey, p_size::DOUBLE AS p_size, p_retailprice::DOUBLE AS p_retailprice FROM part) UNPIVOT (v FOR name IN (p_size, p_retailprice))")(
    lambda s, d: t(s, d, "part").select("p_partkey", F.col("p_size").cast("double"), F.col("p_retailprice").cast("double")).unpivot("p_partkey", ["p_size", "p_retailprice"], "name", "v")
)
query("o27_approx")(lambda s, d: t(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("median"), F.hll_sketch_estimate(F.hll_sketch_agg("l_orderkey")).alias("orders")))
query("o28_corr", "SELECT round(corr(a, b), 8) AS corr, round(covar_pop(a, b), 8) AS covar, round(stddev_pop(a), 8) AS sd_a, round(stddev_pop(b), 8) AS sd_b FROM (SELECT (o_totalprice > 100000)::INT::DOUBLE AS a, (o_totalprice > 200000)::INT::DOUBLE AS b FROM orders)")(
    lambda s, d: r.corr_items(t(s, d, "orders").select((F.col("o_totalprice") > 100000).cast("int").alias("a"), (F.col("o_totalprice") > 200000).cast("int").alias("b")), "a", "b")
)
query("o28_mutual_information", f"WITH {ct('w5')}, x AS (SELECT (m >> 8) & 1 AS a, (m >> 9) & 1 AS b, sum(n) AS n FROM ct GROUP BY ALL) SELECT round(sum(n / tt * log2(n * tt / (na * nb))), 8) AS bits FROM (SELECT n, sum(n) OVER () AS tt, sum(n) OVER (PARTITION BY a) AS na, sum(n) OVER (PARTITION BY b) AS nb FROM x)")(
    lambda s, d: r.mutual_information(WORKLOADS["w5"].compact(s, d), 8, 9)
)
query("o29_having", "SELECT p_brand, count(*) AS count FROM part GROUP BY 1 HAVING count(*) >= 80")(lambda s, d: r.frequent_values(t(s, d, "part"), "p_brand", 80))
query("o30_ranks", "SELECT p_partkey, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY p_type ORDER BY p_retailprice, p_partkey) AS q, round(percent_rank() OVER w, 8) AS pr FROM part WINDOW w AS (PARTITION BY p_type ORDER BY p_size)")(
    lambda s, d: sql_over(s, d, ("part",), "SELECT p_partkey, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY p_type ORDER BY p_retailprice, p_partkey) AS q, round(percent_rank() OVER w, 8) AS pr FROM part WINDOW w AS (PARTITION BY p_type ORDER BY p_size)")
)
query("o30_best_per_group", "SELECT p_type, p_partkey, p_retailprice FROM part QUALIFY row_number() OVER (PARTITION BY p_type ORDER BY p_retailprice DESC, p_partkey) = 1")(
    lambda s, d: r.best_per_group(t(s, d, "part", "p_type", "p_partkey", "p_retailprice"), ["p_type"], [F.desc("p_retailprice"), F.col("p_partkey")])
)
query(
    "o31_shifted",
    "SELECT event_id, event_type, user_id, lag(event_type) OVER w AS prev, lead(event_type) OVER w AS next, first_value(event_type) OVER f AS first, nth_value(event_type, 2) OVER f AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id), f AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
)(lambda s, d: r.shifted(t(s, d, "events", "event_id", "event_type", "user_id", "ts"), "user_id", ["ts", "event_id"], "event_type").drop("ts"))
query("o32_running", "SELECT event_id, round(sum(value) OVER w, 6) AS so_far, round(sum(value) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS last3 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)".replace("sum(value) OVER w,", "sum(value) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW),"))(
    lambda s, d: r.running(t(s, d, "events"), "user_id", ["ts", "event_id"], "value").select("event_id", F.round("so_far", 6).alias("so_far"), F.round("last3", 6).alias("last3"))
)
query("o32_day_range", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY epoch(date_trunc('second', ts)) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW), 6) AS day_sum FROM events")(
    lambda s, d: sql_over(s, d, ("events",), "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY unix_timestamp(cast(ts AS timestamp)) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW), 6) AS day_sum FROM events")
)
query("o33_total_sort", "SELECT p_partkey, row_number() OVER (ORDER BY p_retailprice DESC, p_partkey) AS place FROM part")(lambda s, d: src.global_rank(t(s, d, "part", "p_partkey", "p_retailprice"), [F.desc("p_retailprice"), F.col("p_partkey")], ["p_partkey"]))
query("o34_top_k", f"WITH {ct('w6')} SELECT (1::BIGINT << i) AS mask, sum(n * ((m >> i) & 1))::BIGINT AS supp FROM ct, (SELECT unnest(range(31)) AS i) GROUP BY i ORDER BY supp DESC, mask LIMIT 20")(
    lambda s, d: r.top_k(WORKLOADS["w6"].compact(s, d).select("n", F.explode(F.expr("filter(sequence(0, 30), i -> (shiftright(m, i) & 1) = 1)")).alias("i")).groupBy("i").agg(F.sum("n").alias("supp")).select(F.expr("shiftleft(1L, i)").alias("mask"), "supp"), [F.desc("supp"), F.col("mask")], 20)
)
query("o35_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")(lambda s, d: t(s, d, "customer").select(F.col("c_nationkey").alias("k")).unionByName(t(s, d, "supplier").select(F.col("s_nationkey").alias("k"))).distinct())
query("o36_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")(lambda s, d: t(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(t(s, d, "supplier").select(F.col("s_nationkey").alias("k"))))
query("o36_except_all", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")(lambda s, d: t(s, d, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(t(s, d, "supplier").select(F.col("s_nationkey").alias("k"))))
query("o37_vocabulary", "SELECT token, count(*) AS count FROM (SELECT unnest(list_distinct(regexp_extract_all(lower(text), '[a-z]+'))) AS token FROM documents) GROUP BY 1 ORDER BY count DESC, token LIMIT 120")(lambda s, d: r.vocabulary(t(s, d, "documents", "text"), "text", 120))
query("o37_strings", "SELECT p_partkey, upper(p_name) AS u, string_split(p_name, ' ')[1] AS w, replace(p_brand, '#', '') AS b, length(trim(p_name)) AS n, md5(p_name) AS h FROM part")(
    lambda s, d: t(s, d, "part").select("p_partkey", F.upper("p_name").alias("u"), F.split("p_name", " ")[0].alias("w"), F.replace(F.col("p_brand"), F.lit("#"), F.lit("")).alias("b"), F.length(F.trim("p_name")).cast("long").alias("n"), F.md5("p_name").alias("h"))
)
query("o38_dates", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS dd, isodow(o_orderdate) AS dow, (date_trunc('month', o_orderdate)::DATE)::VARCHAR AS mm, ((o_orderdate + INTERVAL 30 DAY)::DATE)::VARCHAR AS due FROM orders")(
    lambda s, d: t(s, d, "orders").select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"), F.datediff("o_orderdate", F.lit("1995-01-01")).cast("long").alias("dd"), (F.weekday("o_orderdate") + 1).cast("long").alias("dow"), F.date_trunc("month", "o_orderdate").cast("date").cast("string").alias("mm"), (F.col("o_orderdate") + F.expr("INTERVAL 30 DAYS")).cast("date").cast("string").alias("due"))
)
query("o39_bits", f"SELECT key, bit_count(m)::BIGINT AS ones, m & 255 AS low, xor(m, 1) AS flipped, round(sqrt(m), 6) AS root, floor(log2(m + 1))::BIGINT AS top FROM ({WORKLOADS['w5'].packed_sql()})")(
    lambda s, d: WORKLOADS["w5"].packed(s, d).selectExpr("key", "cast(bit_count(m) AS bigint) AS ones", "m & 255 AS low", "m ^ 1L AS flipped", "round(sqrt(m), 6) AS root", "cast(floor(log2(m + 1)) AS bigint) AS top")
)
query("o40_arrays", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS plus, round(list_sum(list_transform(embedding[1:8], lambda x: x::DOUBLE * x::DOUBLE)), 5) AS head, len(list_intersect(range(label::BIGINT), range(5))) AS common FROM embeddings")(
    lambda s, d: t(s, d, "embeddings").select("vec_id", F.expr("cast(size(filter(embedding, x -> x > 0)) AS bigint) AS plus"), F.expr("round(aggregate(transform(slice(embedding, 1, 8), x -> cast(x AS double) * cast(x AS double)), 0D, (a, x) -> a + x), 5) AS head"), F.expr("cast(if(label > 0, size(array_intersect(sequence(0, cast(label AS int) - 1), sequence(0, 4))), 0) AS bigint) AS common"))
)
query("o41_maps", "SELECT o_orderkey, CASE o_orderstatus WHEN 'F' THEN 10 WHEN 'O' THEN 20 END AS v, CASE WHEN o_orderstatus = 'O' THEN 40 END AS doubled FROM orders")(
    lambda s, d: t(s, d, "orders").select("o_orderkey", F.map_from_arrays(F.array(F.lit("F"), F.lit("O")), F.array(F.lit(10), F.lit(20))).alias("m"), "o_orderstatus").select("o_orderkey", F.try_element_at("m", F.col("o_orderstatus")).alias("v"), F.try_element_at(F.transform_values(F.map_filter("m", lambda k, v: v > 10), lambda k, v: v * 2), F.col("o_orderstatus")).alias("doubled"))
)
query("o42_json", "SELECT event_id, json_extract_string(props, '$.k')::INT AS k, '{\"k\":' || (json_extract_string(props, '$.k')::INT + 1) || '}' AS nxt FROM events")(
    lambda s, d: t(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.to_json(F.struct((F.get_json_object("props", "$.k").cast("int") + 1).alias("k"))).alias("nxt"))
)
query("o43_nulls", "SELECT doc_id, coalesce(quality, -1) AS q, nullif(toxic, 0) AS tx, CASE WHEN quality IS NULL THEN 'none' ELSE 'some' END AS has, coalesce(quality = 1, false) AS item FROM documents LEFT JOIN labels USING (doc_id)")(
    lambda s, d: t(s, d, "documents", "doc_id").join(t(s, d, "labels"), "doc_id", "left").selectExpr("doc_id", "coalesce(quality, -1) AS q", "nullif(toxic, 0) AS tx", "nvl2(quality, 'some', 'none') AS has", "coalesce(quality = 1, false) AS item")
)
query("o44_exact_ratio", f"WITH {ct('w9')} SELECT i::INT AS i, round(sum(n * ((m >> i) & 1)) * 1.0 / sum(n), 10)::VARCHAR AS p FROM ct, (SELECT unnest(range(11)) AS i) GROUP BY i".replace("round(sum(n * ((m >> i) & 1)) * 1.0 / sum(n), 10)::VARCHAR", "printf('%.6f', sum(n * ((m >> i) & 1))::DOUBLE / sum(n)::DOUBLE)"))(
    lambda s, d: WORKLOADS["w9"].compact(s, d).crossJoin(F.broadcast(s.range(11).select(F.col("id").cast("int").alias("i")))).groupBy("i").agg(F.sum(F.expr("n * (shiftright(m, i) & 1)")).alias("a"), F.sum("n").alias("b")).select("i", F.format_number(F.try_divide(F.col("a").cast("double"), F.col("b").cast("double")), 6).alias("p"))  # rounds the double's own value, as printf does; a ratio has no thousands
)
query("o45_pages", "SELECT page_id, regexp_extract(html, 'lang=\"(..)\"', 1) AS lang, contains(html, '<nav') AS nav, contains(html, '<table') AS has_table FROM pages")(
    lambda s, d: t(s, d, "pages").select("page_id", F.regexp_extract("html", 'lang="(..)"', 1).alias("lang"), F.contains("html", F.lit("<nav")).alias("nav"), F.contains("html", F.lit("<table")).alias("has_table"))
)
query("o46_conversations", "SELECT conv_id, bool_or(role = 'system') AS sys, bool_or(length(text) > 500) AS long, count(*) AS n FROM conversations GROUP BY 1")(
    lambda s, d: t(s, d, "conversations").groupBy("conv_id").agg(F.bool_or(F.col("role") == "system").alias("sys"), F.bool_or(F.length("text") > 500).alias("long"), F.count("*").alias("n"))
)
query("o47_dedupe", "SELECT md5(text) AS h, min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY 1")(lambda s, d: r.dedupe(t(s, d, "documents").select("doc_id", F.md5("text").alias("h")), ["h"], "doc_id"))
# Leaf complexity of the numbers of lines that parts have.
_M = "SELECT mm::BIGINT AS m, round(log2(sum(exp(lgamma(mm + 1) - lgamma(k + 1) - lgamma(mm - k + 1) + CASE WHEN k > 0 THEN k * ln(k::DOUBLE / mm) ELSE 0 END + CASE WHEN k < mm THEN (mm - k) * ln((mm - k)::DOUBLE / mm) ELSE 0 END))), 6) AS bits FROM (SELECT mm, unnest(range(0, mm + 1)) AS k FROM (SELECT DISTINCT count(*) AS mm FROM lineitem GROUP BY l_partkey)) GROUP BY mm"
query("o48_pandas_udf", _M)(
    lambda s, d: t(s, d, "lineitem", "l_partkey").groupBy("l_partkey").agg(F.count("*").alias("m")).select("m").distinct().select("m", F.round(udfs.nml_bits_udf("m"), 6).alias("bits"))
)
query("o49_aggregate_udf", f"WITH {ct('w9')}, g AS (SELECT i, (m >> 0) & 1 AS leaf, sum(n) AS n, sum(n * ((m >> i) & 1)) AS n1 FROM ct, (SELECT unnest(range(1, 11)) AS i) GROUP BY ALL) SELECT i::INT AS i, round(sum({db('n', 'n1')}), 6) AS bits FROM g GROUP BY i")(
    lambda s, d: WORKLOADS["w9"].compact(s, d).crossJoin(F.broadcast(s.range(1, 11).select(F.col("id").cast("int").alias("i")))).groupBy("i", F.expr("m & 1").alias("leaf")).agg(F.sum("n").alias("n"), F.sum(F.expr("n * (shiftright(m, i) & 1)")).alias("n1")).groupBy("i").agg(udfs.leaf_bits_udaf("n", "n1").alias("bits")).select("i", F.round("bits", 6).alias("bits"))
)
query("o50_table_function", f"WITH {REACHED_SQL} SELECT pos, neg, x::BIGINT AS mask FROM lv, (SELECT unnest(range(4096)) AS x) WHERE x & pos = pos AND x & ~(pos | neg | (1 << target)) = 0")(
    lambda s, d: reached_leaves(s, d).lateralJoin(udfs.leaf_sets_udtf(F.col("pos").outer(), F.col("neg").outer(), F.col("target").outer())).select("pos", "neg", "mask")
)
query("o51_arrow_gram", f"WITH {ct('w5')}, i AS (SELECT unnest(range(18)) AS i) SELECT a.i::INT AS i, b.i::INT AS j, sum(n * ((m >> a.i) & 1) * ((m >> b.i) & 1))::BIGINT AS c FROM ct, i a, i b GROUP BY ALL")(lambda s, d: udfs.gram_table(WORKLOADS["w5"].compact(s, d), 18))
query("o51_grouped_map", "SELECT o_orderstatus AS label, count(*) AS n_rows FROM orders GROUP BY 1")(lambda s, d: udfs.fit_by_class(t(s, d, "orders", "o_orderkey", "o_orderstatus").join(WORKLOADS["w5"].packed(s, d), F.col("o_orderkey") == F.col("key")).select(F.col("o_orderstatus").alias("label"), "m"), 18).select("label", "n_rows"))
query("o52_sql_surface", _M)(
    lambda s, d: udfs.register(s).sql("SELECT m, round(codetrees_nml_bits(m), 6) AS bits FROM (SELECT DISTINCT count(*) AS m FROM {lineitem} GROUP BY l_partkey)", lineitem=t(s, d, "lineitem", "l_partkey"))
)
_SUB = "SELECT p_type, p_partkey FROM part p WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part q WHERE q.p_type = p.p_type) AND EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p.p_partkey AND l_quantity > 45)"
query("o53_subqueries", _SUB)(
    lambda s, d: s.sql("SELECT p_type, p_partkey FROM {part} p WHERE p_retailprice > (SELECT avg(p_retailprice) FROM {part} q WHERE q.p_type = p.p_type) AND EXISTS (SELECT 1 FROM {lineitem} WHERE l_partkey = p.p_partkey AND l_quantity > 45)", part=t(s, d, "part"), lineitem=t(s, d, "lineitem"))
)
query("o54_plan")(lambda s, d: src.plan_table(WORKLOADS["w4"].compact(s, d)))
query("w12_wide_stats")(lambda s, d: src.wide_growth(s, d))
