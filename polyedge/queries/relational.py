"""The relational operators around the methods, with their SQL."""

from __future__ import annotations

from pyspark.sql import Window, functions as F

from polyedge.operators import relational as R
from polyedge.sources import table


def q_scan_pushdown(spark, d):
    return table(spark, d, "lineitem", ["l_orderkey", "l_quantity"], "l_shipdate >= timestamp_ntz'1999-01-01' AND l_discount > 0.05")


def q_project(spark, d):
    return R.project(table(spark, d, "part"), p_partkey="p_partkey", size2="p_size * 2", brand="lower(p_brand)", cents="cast(round(p_retailprice * 100) as bigint)")


def q_filter(spark, d):
    return R.where(table(spark, d, "customer"), "c_acctbal BETWEEN 0 AND 5000 AND c_mktsegment IN ('BUILDING', 'MACHINERY') OR c_name LIKE '%7'").select("c_custkey", "c_mktsegment")


def q_exists(spark, d):
    rich = table(spark, d, "orders", ["o_custkey", "o_totalprice"], "o_totalprice > 300000")
    c = table(spark, d, "customer", ["c_custkey", "c_nationkey"])
    return R.semi(c, rich.withColumnRenamed("o_custkey", "c_custkey"), "c_custkey")


def q_join_star(spark, d):
    li = table(spark, d, "lineitem", ["l_orderkey", "l_extendedprice", "l_discount"])
    o = table(spark, d, "orders", ["o_orderkey", "o_custkey"])
    c = table(spark, d, "customer", ["c_custkey", "c_nationkey"])
    n = table(spark, d, "nation", ["n_nationkey", "n_regionkey"])
    r = table(spark, d, "region", ["r_regionkey", "r_name"])
    j = li.join(o, li.l_orderkey == o.o_orderkey).join(c, F.col("o_custkey") == c.c_custkey)
    j = j.join(F.broadcast(n), j.c_nationkey == n.n_nationkey).join(F.broadcast(r), F.col("n_regionkey") == r.r_regionkey)
    return j.groupBy("r_name").agg(F.count("*").alias("n"), F.sum(F.round(F.col("l_extendedprice") * 100).cast("bigint")).alias("cents"))


def q_join_outer(spark, d):
    c = table(spark, d, "customer", ["c_custkey"])
    o = table(spark, d, "orders", ["o_orderkey", "o_custkey"])
    j = R.join(c, o, c.c_custkey == o.o_custkey, "full")
    return j.groupBy(F.col("c_custkey").isNull().alias("no_customer"), F.col("o_orderkey").isNull().alias("no_order")).agg(F.count("*").alias("n"))


def q_anti(spark, d):
    c = table(spark, d, "customer", ["c_custkey", "c_mktsegment"])
    o = table(spark, d, "orders", ["o_custkey"]).withColumnRenamed("o_custkey", "c_custkey")
    return R.anti(c, o, "c_custkey")


def q_semi(spark, d):
    s = table(spark, d, "supplier", ["s_suppkey", "s_nationkey"])
    li = table(spark, d, "lineitem", ["l_suppkey"], "l_quantity >= 49").withColumnRenamed("l_suppkey", "s_suppkey")
    return R.semi(s, li, "s_suppkey")


def q_interval_truth(spark, d):
    """Days inside scheduled spans."""
    points = table(spark, d, "lineitem").select(F.expr("datediff(l_shipdate, timestamp_ntz'1995-01-01')").cast("bigint").alias("tick"), "l_quantity")
    spans = spark.range(12).select(F.col("id").alias("fault_id"), (F.col("id") * 200 + 10).alias("t0"), (F.col("id") * 200 + 30 + F.col("id")).alias("t1"))
    return R.interval_join(points, spans, "tick", "t0", "t1", 64).groupBy("fault_id").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("qty"))


def q_asof(spark, d):
    e = table(spark, d, "events", ["event_id", "ts", "user_id", "event_type", "value"])
    buys = e.where("event_type = 'purchase'").select("event_id", "ts", "user_id")
    views = e.where("event_type = 'view'").select("ts", "user_id", F.col("value").alias("seen"))
    return R.asof(buys, views, "user_id", "ts", "seen").select("event_id", "seen")


def q_asof_tolerance(spark, d):
    e = table(spark, d, "events", ["event_id", "ts", "user_id", "event_type", "value"])
    buys = e.where("event_type = 'purchase'").select("event_id", "ts", "user_id")
    views = e.where("event_type = 'view'").select("ts", "user_id", F.col("value").alias("seen"))
    return R.asof(buys, views, "user_id", "ts", "seen", tolerance=86_400).select("event_id", "seen")


def q_agg_basic(spark, d):
    return R.agg(table(spark, d, "lineitem"), ["l_returnflag", "l_linestatus"], n="count(*)", qty="sum(cast(l_quantity as bigint))", lo="min(l_extendedprice)", hi="max(l_extendedprice)", orders="count(distinct l_orderkey)")


def q_agg_stats(spark, d):
    return R.agg(table(spark, d, "events"), ["event_type"], mean="round(avg(value), 6)", sd="round(stddev_samp(value), 6)", var="round(var_samp(value), 6)", r="round(corr(value, user_id), 6)", med="round(percentile(value, 0.5), 6)", any_big="bool_or(value > 300)", all_pos="bool_and(value >= 0)")


def q_agg_maxby(spark, d):
    return R.agg(table(spark, d, "orders"), ["o_orderpriority"], top="max_by(o_orderkey, struct(o_totalprice, o_orderkey))", low="min_by(o_orderkey, struct(o_totalprice, o_orderkey))")


def q_distinct(spark, d):
    return R.count_distinct(table(spark, d, "lineitem"), ["l_returnflag"], "l_suppkey")


def q_quantiles(spark, d):
    q = R.quantiles(table(spark, d, "events"), ["event_type"], "value", [0.25, 0.5, 0.75])
    return q.select("event_type", *[F.round(c, 6).alias(c) for c in ("q25", "q50", "q75")])


def _fc(spark, d):
    return table(spark, d, "lineitem", ["l_returnflag", "l_linestatus", "l_quantity"])


def q_cube(spark, d):
    return _fc(spark, d).cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.grouping_id().cast("bigint").alias("gid"))


def q_rollup(spark, d):
    return _fc(spark, d).rollup("l_returnflag", "l_linestatus").agg(F.sum(F.col("l_quantity").cast("bigint")).alias("qty"))


def q_grouping_sets(spark, d):
    sets = [[F.col("l_returnflag")], [F.col("l_linestatus")], []]
    return _fc(spark, d).groupingSets(sets, "l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


def q_rank(spark, d):
    p = table(spark, d, "part", ["p_partkey", "p_brand", "p_size"])
    w = Window.partitionBy("p_brand").orderBy("p_size")
    u = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey")
    return p.select("p_partkey", F.row_number().over(u).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(u).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


def q_lag_lead(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    o = table(spark, d, "orders", ["o_orderkey", "o_custkey", "o_orderdate", "o_totalprice"])
    return o.select("o_orderkey", F.lag("o_orderkey").over(w).alias("prev"), F.lead("o_orderkey").over(w).alias("next"), F.first("o_orderkey").over(w).alias("first"), F.nth_value("o_orderkey", 2).over(w).alias("second"))


def q_frames(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    e = table(spark, d, "events", ["event_id", "user_id", "value"]).withColumn("c", F.round(F.col("value") * 100).cast("bigint"))
    return e.select("event_id", F.sum("c").over(w.rowsBetween(-3, 0)).alias("last4"), F.max("c").over(w.rowsBetween(-5, -1)).alias("before5"), F.count("c").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("run"), F.sum("c").over(w.rangeBetween(-500, 0)).alias("near"))


def q_islands(spark, d):
    e = table(spark, d, "events", ["event_id", "user_id", "value"])
    got = R.islands(e, ["user_id"], "event_id", "value > 50").where("island IS NOT NULL")
    return got.groupBy("user_id", F.col("island").cast("bigint").alias("island")).agg(F.count("*").alias("n"), F.min("event_id").alias("first"))


def q_topk_global(spark, d):
    return R.topk(table(spark, d, "orders", ["o_orderkey", "o_totalprice"]), 20, [F.desc("o_totalprice"), F.asc("o_orderkey")])


def q_topk_group(spark, d):
    return R.topk(table(spark, d, "orders", ["o_orderkey", "o_orderpriority", "o_totalprice"]), 3, [F.desc("o_totalprice"), F.asc("o_orderkey")], ["o_orderpriority"])


def _ck(spark, d):
    a = table(spark, d, "customer", ["c_nationkey"]).withColumnRenamed("c_nationkey", "k")
    b = table(spark, d, "supplier", ["s_nationkey"]).withColumnRenamed("s_nationkey", "k")
    return a, b


def q_union(spark, d):
    a, b = _ck(spark, d)
    return a.unionByName(b).groupBy("k").agg(F.count("*").alias("n"))


def q_intersect(spark, d):
    a, b = _ck(spark, d)
    return a.intersectAll(b)


def q_except(spark, d):
    a, b = _ck(spark, d)
    return a.exceptAll(b)


def q_hash_sample(spark, d):
    return R.hash_sample(table(spark, d, "orders", ["o_orderkey", "o_custkey"]), "o_orderkey", 10, 100)


def q_scalar_subquery(spark, d):
    o = table(spark, d, "orders", ["o_orderkey", "o_totalprice"])
    top = o.agg(F.max("o_totalprice").alias("m"))
    return o.crossJoin(F.broadcast(top)).where("o_totalprice > m * 0.95").select("o_orderkey")


def q_str(spark, d):
    t = table(spark, d, "documents", ["doc_id", "text", "source"])
    return t.select("doc_id", F.length("text").cast("bigint").alias("n"), F.reverse(F.substring("text", 1, 12)).alias("head"), F.regexp_count("text", F.lit("[0-9]+")).cast("bigint").alias("numbers"), F.size(F.split("text", " ")).cast("bigint").alias("words"), F.concat_ws("-", F.trim("source"), F.lpad(F.col("doc_id").cast("string"), 8, "0")).alias("tag"), F.translate(F.substring("text", 1, 20), "aeiou", "AEIOU").alias("vowels"), F.levenshtein(F.col("source"), F.lit("src10")).cast("bigint").alias("lev"))


def q_date(spark, d):
    o = table(spark, d, "orders", ["o_orderkey", "o_orderdate"])
    return o.select("o_orderkey", F.year("o_orderdate").cast("bigint").alias("y"), F.month("o_orderdate").cast("bigint").alias("m"), F.dayofyear("o_orderdate").cast("bigint").alias("doy"), F.date_trunc("week", "o_orderdate").cast("timestamp_ntz").alias("week"), F.expr("datediff(o_orderdate, date'1995-01-01')").cast("bigint").alias("days"), F.expr("o_orderdate + INTERVAL 10 DAY").alias("later"))


def q_math(spark, d):
    li = table(spark, d, "lineitem", ["l_orderkey", "l_linenumber", "l_quantity", "l_discount"])
    return li.select("l_orderkey", "l_linenumber", F.round(F.sqrt("l_quantity"), 6).alias("root"), F.round(F.exp("l_discount"), 6).alias("e"), F.round(F.log("l_quantity"), 6).alias("ln"), F.greatest(F.lit(10.0), "l_quantity").alias("g"), F.pmod(F.col("l_orderkey") * 31, F.lit(97)).cast("bigint").alias("h"), F.round(F.sin("l_quantity"), 6).alias("sine"), F.abs(F.col("l_quantity") - 25).alias("a"))


def q_array_hof(spark, d):
    e = table(spark, d, "embeddings", ["vec_id", "embedding"])
    v = F.transform("embedding", lambda x: x.cast("double"))
    return e.select("vec_id", F.round(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x), 4).alias("norm"), F.size(F.filter(v, lambda x: x > 0)).cast("bigint").alias("positive"), F.exists(v, lambda x: x > 0.4).alias("any_big"), F.forall(v, lambda x: x > -0.9).alias("all_in"))


def q_array_slice(spark, d):
    e = table(spark, d, "embeddings", ["vec_id", "embedding"])
    return e.select("vec_id", F.posexplode(F.slice("embedding", 3, 4)).alias("pos", "x")).select("vec_id", F.col("pos").cast("bigint").alias("pos"), F.round(F.col("x").cast("double"), 6).alias("x"))


def q_map(spark, d):
    e = table(spark, d, "events", ["user_id", "event_type"]).groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = e.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    doubled = F.transform_values("m", lambda k, v: v * 2)
    return m.select("user_id", F.explode(F.map_filter(doubled, lambda k, v: v > 2)).alias("event_type", "n2"))


def q_json(spark, d):
    e = table(spark, d, "events", ["event_id", "props"])
    parsed = F.from_json("props", "k INT")
    return e.select("event_id", parsed["k"].alias("k"), F.get_json_object("props", "$.k").alias("k_text"), F.expr("variant_get(parse_json(props), '$.k', 'int')").alias("k_variant"))


def q_tumbling(spark, d):
    e = table(spark, d, "events", ["ts", "event_type"])
    return e.groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("day"), "event_type", "n")


def q_sliding(spark, d):
    e = table(spark, d, "events", ["ts", "value"])
    return e.groupBy(F.window("ts", "6 hours", "2 hours").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


def q_session(spark, d):
    e = table(spark, d, "events", ["ts", "user_id"])
    got = e.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n"))
    return got.groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"))


def q_skew_join(spark, d):
    li = table(spark, d, "lineitem", ["l_suppkey", "l_quantity"]).withColumnRenamed("l_suppkey", "s_suppkey")
    s = table(spark, d, "supplier", ["s_suppkey", "s_nationkey"])
    return R.skew_join(li, s, "s_suppkey").groupBy("s_nationkey").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("qty"))


def q_theta(spark, d):
    a = table(spark, d, "nation", ["n_nationkey", "n_regionkey"])
    b = a.select(F.col("n_nationkey").alias("k2"), F.col("n_regionkey").alias("r2"))
    return R.theta(a, b, "n_nationkey < k2 AND n_regionkey = r2").select("n_nationkey", "k2")


def q_pages(spark, d):
    return table(spark, d, "pages", ["page_id", "url", "html"]).select("page_id", F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.regexp_count("html", F.lit("<p")).cast("bigint").alias("paragraphs"))


def q_turn_series(spark, d):
    """Conversations as short ordered series: lengths and their changes by turn."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    c = table(spark, d, "conversations", ["conv_id", "turn", "text"]).withColumn("n", F.length("text").cast("bigint"))
    return c.select("conv_id", "turn", "n", (F.col("n") - F.lag("n").over(w)).alias("change"))


QUERIES = {k: v for k, v in globals().items() if k.startswith("q_")}
ASOF = """
WITH v AS (SELECT user_id, ts, max(value) AS seen FROM events WHERE event_type = 'view' GROUP BY ALL)
SELECT b.event_id, {seen} AS seen FROM (SELECT * FROM events WHERE event_type = 'purchase') b ASOF LEFT JOIN v ON b.user_id = v.user_id AND b.ts >= v.ts
"""
ORACLES = {
    "q_scan_pushdown": "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1999-01-01' AND l_discount > 0.05",
    "q_project": "SELECT p_partkey, p_size * 2 AS size2, lower(p_brand) AS brand, CAST(round(p_retailprice * 100) AS BIGINT) AS cents FROM part",
    "q_filter": "SELECT c_custkey, c_mktsegment FROM customer WHERE c_acctbal BETWEEN 0 AND 5000 AND c_mktsegment IN ('BUILDING', 'MACHINERY') OR c_name LIKE '%7'",
    "q_exists": "SELECT c_custkey, c_nationkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)",
    "q_join_star": "SELECT r_name, count(*) AS n, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1",
    "q_join_outer": "SELECT c_custkey IS NULL AS no_customer, o_orderkey IS NULL AS no_order, count(*) AS n FROM customer FULL JOIN orders ON c_custkey = o_custkey GROUP BY 1, 2",
    "q_anti": "SELECT c_custkey, c_mktsegment FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)",
    "q_semi": "SELECT s_suppkey, s_nationkey FROM supplier WHERE s_suppkey IN (SELECT l_suppkey FROM lineitem WHERE l_quantity >= 49)",
    "q_interval_truth": "WITH p AS (SELECT date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS tick, l_quantity FROM lineitem), s AS (SELECT id AS fault_id, id * 200 + 10 AS t0, id * 200 + 30 + id AS t1 FROM range(12) r(id)) SELECT fault_id, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty FROM p JOIN s ON tick BETWEEN t0 AND t1 GROUP BY 1",
    "q_asof": ASOF.format(seen="v.seen"),
    "q_asof_tolerance": ASOF.format(seen="CASE WHEN epoch(b.ts) // 1 - epoch(v.ts) // 1 <= 86400 THEN v.seen END"),
    "q_agg_basic": "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty, min(l_extendedprice) AS lo, max(l_extendedprice) AS hi, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY 1, 2",
    "q_agg_stats": "SELECT event_type, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS sd, round(var_samp(value), 6) AS var, round(corr(value, user_id), 6) AS r, round(quantile_cont(value, 0.5), 6) AS med, bool_or(value > 300) AS any_big, bool_and(value >= 0) AS all_pos FROM events GROUP BY 1",
    "q_agg_maxby": "SELECT o_orderpriority, (array_agg(o_orderkey ORDER BY o_totalprice DESC, o_orderkey DESC))[1] AS top, (array_agg(o_orderkey ORDER BY o_totalprice, o_orderkey))[1] AS low FROM orders GROUP BY 1",
    "q_distinct": "SELECT l_returnflag, count(DISTINCT l_suppkey) AS n FROM lineitem GROUP BY 1",
    "q_quantiles": "SELECT event_type, round(quantile_cont(value, 0.25), 6) AS q25, round(quantile_cont(value, 0.5), 6) AS q50, round(quantile_cont(value, 0.75), 6) AS q75 FROM events GROUP BY 1",
    "q_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(grouping(l_returnflag, l_linestatus) AS BIGINT) AS gid FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "q_rollup": "SELECT l_returnflag, l_linestatus, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "q_grouping_sets": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    "q_rank": "SELECT p_partkey, CAST(row_number() OVER u AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, CAST(ntile(4) OVER u AS INTEGER) AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size), u AS (PARTITION BY p_brand ORDER BY p_size, p_partkey)",
    "q_lag_lead": "SELECT o_orderkey, lag(o_orderkey) OVER w AS prev, lead(o_orderkey) OVER w AS next, first_value(o_orderkey) OVER w AS first, nth_value(o_orderkey, 2) OVER w AS second FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)",
    "q_frames": "WITH e AS (SELECT event_id, user_id, CAST(round(value * 100) AS BIGINT) AS c FROM events) SELECT event_id, CAST(sum(c) OVER (w ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS BIGINT) AS last4, max(c) OVER (w ROWS BETWEEN 5 PRECEDING AND 1 PRECEDING) AS before5, count(c) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS run, CAST(sum(c) OVER (w RANGE BETWEEN 500 PRECEDING AND CURRENT ROW) AS BIGINT) AS near FROM e WINDOW w AS (PARTITION BY user_id ORDER BY event_id)",
    "q_islands": "WITH a AS (SELECT *, value > 50 AS ok, coalesce(lag(value > 50) OVER (PARTITION BY user_id ORDER BY event_id), false) AS was FROM events), b AS (SELECT *, sum(CASE WHEN ok AND NOT was THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY event_id) AS island FROM a) SELECT user_id, CAST(island AS BIGINT) AS island, count(*) AS n, min(event_id) AS first FROM b WHERE ok GROUP BY 1, 2",
    "q_topk_global": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20",
    "q_topk_group": "SELECT o_orderkey, o_orderpriority, o_totalprice FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) <= 3",
    "q_union": "SELECT k, count(*) AS n FROM (SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier) GROUP BY 1",
    "q_intersect": "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier",
    "q_except": "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier",
    "q_hash_sample": "SELECT o_orderkey, o_custkey FROM orders WHERE (o_orderkey * 2654435761) % 100 < 10",
    "q_scalar_subquery": "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT max(o_totalprice) FROM orders) * 0.95",
    "q_str": "SELECT doc_id, length(text) AS n, reverse(substring(text, 1, 12)) AS head, CAST(len(regexp_extract_all(text, '[0-9]+')) AS BIGINT) AS numbers, CAST(len(string_split(text, ' ')) AS BIGINT) AS words, concat_ws('-', trim(source), lpad(CAST(doc_id AS VARCHAR), 8, '0')) AS tag, translate(substring(text, 1, 20), 'aeiou', 'AEIOU') AS vowels, NULL AS lev FROM documents",
    "q_date": "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, dayofyear(o_orderdate) AS doy, CAST(date_trunc('week', o_orderdate) AS TIMESTAMP) AS week, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS days, o_orderdate + INTERVAL 10 DAY AS later FROM orders",
    "q_math": "SELECT l_orderkey, l_linenumber, round(sqrt(l_quantity), 6) AS root, round(exp(l_discount), 6) AS e, round(ln(l_quantity), 6) AS ln, greatest(10.0::DOUBLE, l_quantity) AS g, (l_orderkey * 31) % 97 AS h, round(sin(l_quantity), 6) AS sine, abs(l_quantity - 25) AS a FROM lineitem",
    "q_array_hof": "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS norm, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS positive, len(list_filter(embedding, lambda x: CAST(x AS DOUBLE) > 0.4::DOUBLE)) > 0 AS any_big, len(list_filter(embedding, lambda x: NOT (CAST(x AS DOUBLE) > -0.9::DOUBLE))) = 0 AS all_in FROM embeddings",
    "q_array_slice": "SELECT vec_id, generate_subscripts(embedding[3:6], 1) - 1 AS pos, round(CAST(unnest(embedding[3:6]) AS DOUBLE), 6) AS x FROM embeddings",
    "q_map": "SELECT user_id, event_type, count(*) * 2 AS n2 FROM events GROUP BY 1, 2 HAVING count(*) * 2 > 2",
    "q_json": "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k, json_extract_string(props, '$.k') AS k_text, CAST(json_extract(props, '$.k') AS INTEGER) AS k_variant FROM events",
    "q_tumbling": "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "q_sliding": "WITH b AS (SELECT time_bucket(INTERVAL 2 HOUR, ts, TIMESTAMP '1970-01-01') AS t FROM events) SELECT t - INTERVAL 2 HOUR * k AS start, count(*) AS n FROM b CROSS JOIN (SELECT unnest([0, 1, 2]) AS k) GROUP BY 1",
    "q_session": "WITH a AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS b FROM events), s AS (SELECT user_id, sum(b) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS s FROM a), c AS (SELECT user_id, s, count(*) AS n FROM s GROUP BY 1, 2) SELECT user_id, count(*) AS sessions, max(n) AS longest FROM c GROUP BY 1",
    "q_skew_join": "SELECT s_nationkey, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1",
    "q_theta": "SELECT a.n_nationkey, b.n_nationkey AS k2 FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey",
    "q_pages": "SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, CAST(len(regexp_extract_all(html, '<p')) AS BIGINT) AS paragraphs FROM pages",
    "q_turn_series": "SELECT conv_id, turn, length(text) AS n, length(text) - lag(length(text)) OVER (PARTITION BY conv_id ORDER BY turn) AS change FROM conversations",
}
ORACLES["q_str"] = ORACLES["q_str"].replace("NULL AS lev", "levenshtein(source, 'src10') AS lev")
