"""Queries on the operators around the methods: scans, joins, aggregates, windows, sets, functions, SQL text."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import vectors
from ..operators import relational as ops
from ..operators import topology
from ..plans.sqlapi import register_views
from ..sources.tables import read_table
from .base import RADIX, TRADE, H, query, r6, radix_sql
from .network import IMG, images, lit_links, lit_sql


def T(spark, d, *names):
    out = [read_table(spark, d, n) for n in names]
    return out[0] if len(out) == 1 else out


@query("scan_filter_project", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_shipdate >= TIMESTAMP '1996-01-01'")
def _(spark, d):
    li = T(spark, d, "lineitem").filter(F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R") & (F.col("l_shipdate") >= F.lit("1996-01-01").cast("timestamp")))
    return li.select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("filter_like_null", "SELECT count(*) AS n FROM part WHERE p_type LIKE '%E%' AND p_brand IS NOT NULL AND NOT (p_size > 40)")
def _(spark, d):
    return T(spark, d, "part").filter(F.col("p_type").like("%E%") & F.col("p_brand").isNotNull() & ~(F.col("p_size") > 40)).agg(F.count(F.lit(1)).alias("n"))


@query("distinct_pairs", "SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")
def _(spark, d):
    return T(spark, d, "lineitem").select("l_partkey", "l_suppkey").distinct()


_JOIN = "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"
for _name, _hint in (("join_hash", "shuffle_hash"), ("join_merge", "merge")):

    @query(_name, _JOIN)
    def _(spark, d, hint=_hint):
        li, o = T(spark, d, "lineitem", "orders")
        return li.join(o.hint(hint), li.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


@query("join_broadcast", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def _(spark, d):
    c, n, r = T(spark, d, "customer", "nation", "region")
    small = n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey)  # 25 nations
    return c.join(F.broadcast(small), c.c_nationkey == n.n_nationkey).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


@query("join_colocated", f'WITH {radix_sql(*RADIX)} SELECT a."row", sum(a.w * b.w) AS s FROM rw a JOIN rw b ON a."row" = b."row" AND a.col = b.col WHERE a.layer = 1 AND b.layer = 3 GROUP BY 1')
def _(spark, d):
    net = topology.radix_network(spark, RADIX[0], RADIX[1], RADIX[2])
    part = (F.col("row") % 4).cast("int")
    a = net.layer(1).withColumn("part", part).repartitionById(4, F.col("part"))
    b = net.layer(3).withColumn("part", part).withColumnRenamed("w", "v").repartitionById(4, F.col("part"))
    return a.hint("merge").join(b, ["part", "row", "col"]).groupBy("part", "row").agg(F.sum(F.col("w") * F.col("v")).alias("s")).drop("part")


@query("join_range", "SELECT b.band::INTEGER AS band, count(*) AS n FROM part p JOIN (SELECT range AS band, 900 + range * 50 AS low, 950 + range * 50 AS high FROM range(24)) b ON p.p_retailprice >= b.low AND p.p_retailprice < b.high GROUP BY 1")
def _(spark, d):
    bands = spark.range(24).select(F.col("id").cast("int").alias("band"), (900 + F.col("id") * 50).cast("double").alias("low"), (950 + F.col("id") * 50).cast("double").alias("high"))
    return ops.range_join(T(spark, d, "part"), bands, "p_retailprice", "low", "high", 50.0).groupBy("band").agg(F.count(F.lit(1)).alias("n"))


_ASOF = "SELECT p.event_id, coalesce((SELECT v.event_id FROM events v WHERE v.event_type = 'view' AND v.user_id = p.user_id AND v.ts <= p.ts ORDER BY v.ts DESC, v.event_id DESC LIMIT 1), -1) AS view_id FROM events p WHERE p.event_type = 'purchase'"


@query("join_asof", _ASOF)
def _(spark, d):
    e = T(spark, d, "events")
    left = e.filter("event_type = 'purchase'").select("event_id", "user_id", "ts")
    right = e.filter("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("view_id"))
    return ops.asof_join(left, right, "user_id", "ts", "view_id", "view_id").select("event_id", F.coalesce("view_id", F.lit(-1)).alias("view_id"))


@query("join_interval", "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 6 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def _(spark, d):
    e = T(spark, d, "events")
    c = e.filter("event_type = 'click'").select("user_id", F.col("ts").alias("c_ts"), F.col("event_id").alias("click_id"))
    p = e.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("p_ts"), F.col("event_id").alias("purchase_id"))
    return c.join(p, "user_id").filter("p_ts >= c_ts and p_ts <= c_ts + interval 6 hours").select("click_id", "purchase_id")


@query("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def _(spark, d):
    c, o = T(spark, d, "customer", "orders")
    return c.join(o, c.c_custkey == o.o_custkey, "left_semi").select("c_custkey")


@query("join_anti", "SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 49)")
def _(spark, d):
    p, li = T(spark, d, "part", "lineitem")
    return p.join(li.filter("l_quantity > 49"), p.p_partkey == li.l_partkey, "left_anti").select("p_partkey")


@query("join_full", "SELECT coalesce(a.n_nationkey, b.s_nationkey) AS nation, coalesce(a.n, 0) AS customers, coalesce(b.m, 0) AS suppliers FROM (SELECT c_nationkey AS n_nationkey, count(*) AS n FROM customer GROUP BY 1) a FULL JOIN (SELECT s_nationkey, count(*) AS m FROM supplier GROUP BY 1) b ON a.n_nationkey = b.s_nationkey")
def _(spark, d):
    c, s = T(spark, d, "customer", "supplier")
    a = c.groupBy(F.col("c_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("customers"))
    b = s.groupBy(F.col("s_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("suppliers"))
    return a.join(b, "nation", "full").select("nation", F.coalesce("customers", F.lit(0)).alias("customers"), F.coalesce("suppliers", F.lit(0)).alias("suppliers"))


@query("join_cross", "SELECT r_name, n_name FROM region, nation WHERE n_regionkey <> r_regionkey")
def _(spark, d):
    r, n = T(spark, d, "region", "nation")
    return r.crossJoin(F.broadcast(n)).filter("n_regionkey <> r_regionkey").select("r_name", "n_name")  # 5 x 25 rows


@query("join_self_cooccurrence", f'WITH {TRADE} SELECT a."row" AS a, b."row" AS b, count(*) AS shared FROM te a JOIN te b ON a.layer = b.layer AND a.col = b.col AND a."row" < b."row" WHERE a.layer = 2 GROUP BY 1, 2')
def _(spark, d):
    return ops.shared_inputs(topology.trade_edges(spark, d).filter("layer = 2"))


@query("lateral_top", "SELECT c_nationkey, c_custkey, c_acctbal FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS nth FROM customer) WHERE nth <= 2")
def _(spark, d):
    T(spark, d, "customer").createOrReplaceTempView("lateral_customer")
    T(spark, d, "nation").createOrReplaceTempView("lateral_nation")
    return spark.sql("SELECT c_nationkey, c_custkey, c_acctbal FROM lateral_nation n, LATERAL (SELECT c_nationkey, c_custkey, c_acctbal FROM lateral_customer c WHERE c.c_nationkey = n.n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2)")


@query("correlated_scalar", "SELECT p_partkey FROM part WHERE p_retailprice > (SELECT avg(l_extendedprice / l_quantity) FROM lineitem WHERE l_partkey = p_partkey)")
def _(spark, d):
    T(spark, d, "part").createOrReplaceTempView("scalar_part")
    T(spark, d, "lineitem").createOrReplaceTempView("scalar_lineitem")
    return spark.sql("SELECT p_partkey FROM scalar_part p WHERE p_retailprice > (SELECT avg(l_extendedprice / l_quantity) FROM scalar_lineitem l WHERE l.l_partkey = p.p_partkey)")


@query("agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS qty, round(avg(l_extendedprice), 4) AS price, min(l_discount) AS least, max(l_tax) AS most FROM lineitem GROUP BY 1, 2")
def _(spark, d):
    return T(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.min("l_discount").alias("least"), F.max("l_tax").alias("most"))


@query("agg_collect_lists", "SELECT n_regionkey, array_to_string(list_sort(list(n_name)), ',') AS names FROM nation GROUP BY 1")
def _(spark, d):
    return T(spark, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"))


_G = "SELECT coalesce(o_orderstatus, '*') AS status, coalesce(o_orderpriority, '*') AS priority, count(*) AS n FROM orders GROUP BY {}"
for _name, _by in (("agg_grouping_sets", "GROUPING SETS ((o_orderstatus), (o_orderpriority), ())"), ("agg_rollup", "ROLLUP (o_orderstatus, o_orderpriority)"), ("agg_cube", "CUBE (o_orderstatus, o_orderpriority)")):

    @query(_name, _G.format(_by))
    def _(spark, d, by=_by):
        T(spark, d, "orders").createOrReplaceTempView("grouping_orders")
        return spark.sql(_G.format(by).replace("FROM orders", "FROM grouping_orders"))


@query("agg_distinct", "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY 1")
def _(spark, d):
    return T(spark, d, "lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_orderkey").alias("orders"))


@query("agg_approx_distinct")
def _(spark, d):
    return T(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_quantity", [0.5, 0.9]).alias("quantiles"))


@query("agg_hll_sketch")
def _(spark, d):
    s = T(spark, d, "lineitem").groupBy("l_linestatus").agg(F.hll_sketch_agg("l_partkey").alias("s"))
    return s.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("parts"))


@query("agg_bitmask_connectivity", "SELECT l_partkey, count(DISTINCT l_suppkey % 32)::INTEGER AS lam FROM lineitem GROUP BY 1")
def _(spark, d):
    return T(spark, d, "lineitem").groupBy("l_partkey").agg(F.bit_count(F.bit_or(F.expr("shiftleft(CAST(1 AS BIGINT), CAST(l_suppkey % 32 AS INT))"))).alias("lam"))


@query("agg_pivot", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events WHERE event_type IN ('click', 'view') GROUP BY 1")
def _(spark, d):
    p = T(spark, d, "events").filter("event_type in ('click', 'view')").groupBy("user_id").pivot("event_type", ["click", "view"]).count()
    return p.na.fill(0)


@query("agg_unpivot", "SELECT p_partkey, 'p_size' AS what, p_size::DOUBLE AS v FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part")
def _(spark, d):
    p = T(spark, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice")
    return p.unpivot("p_partkey", ["p_size", "p_retailprice"], "what", "v")


@query("agg_conditional", "SELECT l_shipdate::DATE AS day, count(*) FILTER (WHERE l_returnflag = 'R') AS returned, sum(CASE WHEN l_discount > 0.05 THEN l_quantity ELSE 0 END) AS cheap FROM lineitem GROUP BY 1")
def _(spark, d):
    return T(spark, d, "lineitem").groupBy(F.to_date("l_shipdate").alias("day")).agg(F.count_if(F.col("l_returnflag") == "R").alias("returned"), F.sum(F.when(F.col("l_discount") > 0.05, F.col("l_quantity")).otherwise(0.0)).alias("cheap"))


@query("agg_argmax", "SELECT l_suppkey, arg_max(l_partkey, l_extendedprice * 1e6 - l_orderkey * 1e-3) AS part, bool_and(l_quantity > 0) AS positive FROM lineitem GROUP BY 1")
def _(spark, d):
    return T(spark, d, "lineitem").groupBy("l_suppkey").agg(F.max_by("l_partkey", F.col("l_extendedprice") * 1e6 - F.col("l_orderkey") * 1e-3).alias("part"), F.bool_and(F.col("l_quantity") > 0).alias("positive"))


@query("agg_statistics", "SELECT l_returnflag, round(stddev_pop(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_pop(l_quantity, l_discount), 6) AS cov FROM lineitem GROUP BY 1")
def _(spark, d):
    return T(spark, d, "lineitem").groupBy("l_returnflag").agg(r6(F.stddev_pop("l_quantity")).alias("sd"), r6(F.corr("l_quantity", "l_extendedprice")).alias("r"), r6(F.covar_pop("l_quantity", "l_discount")).alias("cov"))


@query("agg_histogram", "SELECT floor(l_quantity / 5)::BIGINT AS bucket, count(*) AS n FROM lineitem GROUP BY 1")
def _(spark, d):
    return T(spark, d, "lineitem").groupBy(F.floor(F.col("l_quantity") / 5).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


@query("degree_histogram", f'WITH {TRADE} SELECT layer, n AS degree, count(*) AS n_rows FROM (SELECT layer, "row", count(*) AS n FROM te GROUP BY 1, 2) GROUP BY 1, 2')
def _(spark, d):
    by = topology.trade_edges(spark, d).groupBy("layer", "row").agg(F.count(F.lit(1)).alias("degree"))
    return by.groupBy("layer", "degree").agg(F.count(F.lit(1)).alias("n_rows"))


@query("window_rank", "SELECT c_custkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS q, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey), v AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)")
def _(spark, d):
    w, v = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey"), Window.partitionBy("c_nationkey").orderBy("c_mktsegment")
    return T(spark, d, "customer").select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("q"), r6(F.percent_rank().over(w)).alias("pr"), r6(F.cume_dist().over(w)).alias("cd"))


@query("window_lag_lead", "SELECT event_id, lag(event_id, 1, -1) OVER w AS before, lead(event_id, 2, -1) OVER w AS after, first_value(event_id) OVER w AS first, coalesce(nth_value(event_id, 2) OVER w, -1) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return T(spark, d, "events").select("event_id", F.lag("event_id", 1, -1).over(w).alias("before"), F.lead("event_id", 2, -1).over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.coalesce(F.nth_value("event_id", 2).over(w), F.lit(-1)).alias("second"))


@query("window_running", "SELECT l_orderkey, l_linenumber, l_partkey, sum(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice ROWS UNBOUNDED PRECEDING) AS running FROM lineitem")
def _(spark, d):
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice").rowsBetween(Window.unboundedPreceding, 0)
    return T(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.sum("l_quantity").over(w).alias("running"))


@query("window_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS in_day FROM (SELECT event_id, user_id, date_trunc('second', ts) AS ts FROM events)")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy(F.unix_timestamp(F.date_trunc("second", "ts"))).rangeBetween(-86400, 0)
    return T(spark, d, "events").select("event_id", F.count(F.lit(1)).over(w).alias("in_day"))


@query("window_share", "SELECT s_suppkey, round(s_acctbal / sum(abs(s_acctbal)) OVER (PARTITION BY s_nationkey), 6) AS share FROM supplier")
def _(spark, d):
    return T(spark, d, "supplier").select("s_suppkey", r6(F.col("s_acctbal") / F.sum(F.abs("s_acctbal")).over(Window.partitionBy("s_nationkey"))).alias("share"))


@query("topk_per_row", f'WITH {TRADE} SELECT "row", col, w FROM (SELECT "row", col, w, row_number() OVER (PARTITION BY "row" ORDER BY abs(w) DESC, col) AS nth FROM tw WHERE layer = 2) WHERE nth <= 3')
def _(spark, d):
    return ops.heaviest_links(topology.trade_network(spark, d).weights.filter("layer = 2"), 3).select("row", "col", "w")


@query("global_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25 OFFSET 5")
def _(spark, d):
    return T(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(25).select("o_orderkey", "o_totalprice")


@query("sort_within_parts")
def _(spark, d):
    return topology.trade_network(spark, d).weights.repartition(4, "layer").sortWithinPartitions("layer", "row", "col")


@query("sample_by_hash", f"SELECT vec_id FROM embeddings ORDER BY {H('vec_id', chr(39) + 'sample' + chr(39), 0)}, vec_id LIMIT 200")
def _(spark, d):
    return ops.hash_sample(T(spark, d, "embeddings"), "vec_id", 200).select("vec_id")


@query("set_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def _(spark, d):
    c, s = T(spark, d, "customer", "supplier")
    return c.select(F.col("c_nationkey").alias("k")).intersect(s.select("s_nationkey"))


@query("set_except", "SELECT p_partkey AS k FROM part EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity < 3")
def _(spark, d):
    p, li = T(spark, d, "part", "lineitem")
    return p.select(F.col("p_partkey").alias("k")).exceptAll(li.filter("l_quantity < 3").select("l_partkey").distinct())


@query("set_union", "SELECT n_name AS name FROM nation UNION ALL SELECT r_name FROM region")
def _(spark, d):
    n, r = T(spark, d, "nation", "region")
    return n.select(F.col("n_name").alias("name")).unionByName(r.select(F.col("r_name").alias("name")))


@query("json_props", "SELECT event_id, (props::JSON ->> 'k')::BIGINT AS k FROM events")
def _(spark, d):
    return T(spark, d, "events").select("event_id", F.from_json("props", "k BIGINT")["k"].alias("k"))


@query("date_month_features", "SELECT o_orderkey, date_trunc('month', o_orderdate)::DATE AS month, isodow(o_orderdate)::INTEGER AS dow, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INTEGER AS days FROM orders")
def _(spark, d):
    dow = (F.weekday("o_orderdate") + 1).cast("int")
    return T(spark, d, "orders").select("o_orderkey", F.to_date(F.date_trunc("month", "o_orderdate")).alias("month"), dow.alias("dow"), F.datediff(F.to_date("o_orderdate"), F.lit("1995-01-01")).alias("days"))


@query("string_tokens", "SELECT p_partkey, lower(p_name) AS name, length(p_name)::INTEGER AS n, split_part(p_type, ' ', 1) AS kind, replace(p_brand, '#', '-') AS brand FROM part")
def _(spark, d):
    return T(spark, d, "part").select("p_partkey", F.lower("p_name").alias("name"), F.length("p_name").alias("n"), F.split_part("p_type", F.lit(" "), F.lit(1)).alias("kind"), F.translate("p_brand", "#", "-").alias("brand"))


@query("array_ops", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS norm2, len(list_filter(embedding, lambda x: x > 0))::INTEGER AS positive, (list_position(list_transform(embedding, lambda x: x::DOUBLE), list_max(list_transform(embedding, lambda x: x::DOUBLE))) - 1)::INTEGER AS peak FROM embeddings")
def _(spark, d):
    e = T(spark, d, "embeddings").withColumn("v", F.transform("embedding", lambda x: x.cast("double")))
    return e.select("vec_id", r6(vectors.dot(F.col("v"), F.col("v"))).alias("norm2"), F.size(F.filter("v", lambda x: x > 0)).alias("positive"), vectors.argmax(F.col("v")).alias("peak"))


@query("map_ops", "SELECT l_suppkey, count(*) FILTER (WHERE l_linestatus = 'F') + 2 * count(*) FILTER (WHERE l_linestatus = 'O') AS weighted FROM lineitem GROUP BY 1")
def _(spark, d):
    by = T(spark, d, "lineitem").groupBy("l_suppkey", "l_linestatus").agg(F.count(F.lit(1)).alias("n")).groupBy("l_suppkey").agg(F.map_from_entries(F.collect_list(F.struct("l_linestatus", "n"))).alias("m"))
    scaled = F.map_zip_with("m", F.create_map(F.lit("F"), F.lit(1), F.lit("O"), F.lit(2)), lambda k, n, f: F.coalesce(n, F.lit(0)) * F.coalesce(f, F.lit(0)))
    return by.select("l_suppkey", F.aggregate(F.map_values(scaled), F.lit(0).cast("bigint"), lambda s, x: s + x).alias("weighted"))


@query("safe_arithmetic", "SELECT s_suppkey, CASE WHEN s_nationkey = 0 THEN NULL ELSE round(s_acctbal / s_nationkey, 6) END AS per, coalesce(nullif(s_nationkey, 3), -1) AS nation FROM supplier")
def _(spark, d):
    return T(spark, d, "supplier").select("s_suppkey", r6(F.try_divide("s_acctbal", "s_nationkey")).alias("per"), F.coalesce(F.nullif(F.col("s_nationkey"), F.lit(3)), F.lit(-1)).alias("nation"))


@query("vector_helpers", "SELECT vec_id, round(list_sum(list_transform(list_zip(embedding, embedding), lambda p: p[1]::DOUBLE * (2.0 * p[1]::DOUBLE + p[2]::DOUBLE))), 6) AS mixed, (label % 4)::INTEGER AS hot FROM embeddings")
def _(spark, d):
    e = T(spark, d, "embeddings").withColumn("v", F.transform("embedding", lambda x: x.cast("double")))
    mixed = F.aggregate(vectors.hadamard(F.col("v"), vectors.axpy(F.lit(2.0), F.col("v"), F.col("v"))), F.lit(0.0), lambda s, x: s + x)
    return e.select("vec_id", r6(mixed).alias("mixed"), vectors.argmax(vectors.one_hot(F.col("label") % 4, 4)).alias("hot"))


@query("sql_functions", "SELECT vec_id, round(1 / (1 + exp(-label::DOUBLE)), 6) AS s, round((1 / (1 + exp(-label::DOUBLE))) * (1 - 1 / (1 + exp(-label::DOUBLE))), 6) AS p, " + H("vec_id", 3, 0) + " AS h FROM embeddings")
def _(spark, d):
    vectors.register_sql_functions(spark)
    T(spark, d, "embeddings").createOrReplaceTempView("sql_embeddings")
    return spark.sql("SELECT vec_id, round(sigmoid(CAST(label AS DOUBLE)), 6) AS s, round(sigmoid_prime(sigmoid(CAST(label AS DOUBLE))), 6) AS p, portable_hash(vec_id, 3, 0) AS h FROM sql_embeddings")


@query("sql_text_spmv", f'WITH {radix_sql(*RADIX)} SELECT "row", sum(w) AS z FROM rw WHERE layer = 1 GROUP BY 1')
def _(spark, d):
    net = topology.radix_network(spark, RADIX[0], RADIX[1], RADIX[2])
    register_views(spark, net)
    return spark.sql("SELECT w.row, sum(w.w * x.x) AS z FROM net_weights w JOIN (SELECT neuron, CAST(1 AS DOUBLE) AS x FROM net_neurons WHERE layer = 0) x ON w.col = x.neuron WHERE w.layer = 1 GROUP BY w.row")


@query("table_function_radix", 'SELECT r.range AS "row", (r.range + n.range * 8) % 64 AS col FROM range(64) r, range(8) n')
def _(spark, d):
    from ..sources.generators import register_generators

    register_generators(spark)
    return spark.sql("SELECT row, col FROM mixed_radix_rows(64, 8, 8)")


@query("data_source_radix", f"""WITH {radix_sql(64, 4, 8)}, rl AS (SELECT layer, "row", col FROM rw), {IMG} {lit_sql('rl')}""")
def _(spark, d):
    from ..sources.generators import register_generators

    register_generators(spark)
    return lit_links(spark.read.format("mixedradix").option("neurons", 64).option("layers", 4).option("degree", 8).load(), images(spark, d))


@query("threshold_image_udf", "SELECT vec_id, list_sum(list_transform(embedding, lambda x: (x > 0)::INTEGER))::BIGINT AS n FROM embeddings")
def _(spark, d):
    return T(spark, d, "embeddings").select("vec_id", F.aggregate(ops.threshold_image(F.col("embedding")), F.lit(0).cast("bigint"), lambda s, x: s + x).alias("n"))
