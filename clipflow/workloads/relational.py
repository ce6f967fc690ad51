"""Relational operators that users of the methods need, on the star tables (X)."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from clipflow.sources.standin import epoch
from clipflow.sources.tables import load
from clipflow.workloads.registry import query

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@query("x_scan_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def x_scan_counts(spark, d):
    out = None
    for t in TABLES:
        c = load(spark, d, t).agg(F.count(F.lit(1)).alias("n")).select(F.lit(t).alias("name"), "n")
        out = c if out is None else out.unionByName(c)
    return out


@query("x_project", "SELECT o_orderkey, upper(o_orderpriority) AS priority, round(o_totalprice * 1.1, 4) AS gross, year(o_orderdate)::INT AS y FROM orders")
def x_project(spark, d):
    o = load(spark, d, "orders", "o_orderkey", "o_orderpriority", "o_totalprice", "o_orderdate")
    return o.select("o_orderkey", F.upper("o_orderpriority").alias("priority"), F.round(F.col("o_totalprice") * 1.1, 4).alias("gross"), F.year("o_orderdate").alias("y"))


@query("x_filter_compound", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE (l_quantity BETWEEN 10 AND 20 OR l_returnflag IN ('R')) AND l_linestatus <> 'F' AND l_shipdate >= TIMESTAMP '1996-01-01'")
def x_filter_compound(spark, d):
    li = load(spark, d, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_returnflag", "l_linestatus", "l_shipdate")
    li = li.where("(l_quantity BETWEEN 10 AND 20 OR l_returnflag IN ('R')) AND l_linestatus <> 'F' AND l_shipdate >= TIMESTAMP_NTZ'1996-01-01 00:00:00'")
    return li.select("l_orderkey", "l_linenumber", "l_quantity")


@query("x_join_broadcast", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")
def x_join_broadcast(spark, d):
    """Nations and regions are 25 and 5 rows at any scale."""
    n = load(spark, d, "nation").join(F.broadcast(load(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    c = load(spark, d, "customer", "c_nationkey").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
    return c.groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


@query("x_join_merge", "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def x_join_merge(spark, d):
    o, li = load(spark, d, "orders", "o_orderkey", "o_orderpriority"), load(spark, d, "lineitem", "l_orderkey", "l_quantity")
    j = o.hint("merge").join(li, F.col("o_orderkey") == F.col("l_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))


@query("x_join_semi_anti", "SELECT 'with' AS kind, count(*) AS n FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey) UNION ALL SELECT 'without', count(*) FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def x_join_semi_anti(spark, d):
    o, li = load(spark, d, "orders", "o_orderkey"), load(spark, d, "lineitem", F.col("l_orderkey").alias("o_orderkey"))
    count = lambda how, name: o.join(li, "o_orderkey", how).agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("kind"), "n")
    return count("left_semi", "with").unionByName(count("left_anti", "without"))


@query("x_join_full", "SELECT coalesce(c_nationkey, s_nationkey) AS nationkey, coalesce(nc, 0) AS n_customers, coalesce(ns, 0) AS n_suppliers FROM (SELECT c_nationkey, count(*) AS nc FROM customer GROUP BY 1) FULL JOIN (SELECT s_nationkey, count(*) AS ns FROM supplier GROUP BY 1) ON c_nationkey = s_nationkey")
def x_join_full(spark, d):
    c = load(spark, d, "customer", F.col("c_nationkey").alias("nationkey")).groupBy("nationkey").agg(F.count(F.lit(1)).alias("n_customers"))
    s = load(spark, d, "supplier", F.col("s_nationkey").alias("nationkey")).groupBy("nationkey").agg(F.count(F.lit(1)).alias("n_suppliers"))
    return c.join(s, "nationkey", "full").fillna(0, ["n_customers", "n_suppliers"])


@query("x_join_interval", "WITH s AS (SELECT s_suppkey, s_acctbal AS lo, s_acctbal + 50 AS hi FROM supplier) SELECT s_suppkey, count(*) AS n FROM s JOIN customer ON c_acctbal BETWEEN lo AND hi GROUP BY 1")
def x_join_interval(spark, d):
    """Points in intervals by buckets of the interval's width: an equi-join with at most two buckets an interval."""
    s = load(spark, d, "supplier", "s_suppkey", F.col("s_acctbal").alias("lo")).withColumn("hi", F.col("lo") + 50)
    s = s.withColumn("b", F.explode(F.sequence(F.floor(F.col("lo") / 50), F.floor(F.col("hi") / 50))))
    c = load(spark, d, "customer", "c_acctbal").withColumn("b", F.floor(F.col("c_acctbal") / 50))
    return s.join(c, "b").where("c_acctbal BETWEEN lo AND hi").groupBy("s_suppkey").agg(F.count(F.lit(1)).alias("n"))


@query("x_join_asof", """WITH q AS (SELECT DISTINCT user_id, date_trunc('day', ts) + INTERVAL 12 HOUR AS at FROM events)
    SELECT q.user_id, epoch(q.at)::BIGINT AS at, e.event_id FROM q ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events GROUP BY 1, 2) e ON e.user_id = q.user_id AND e.ts <= q.at""")
def x_join_asof(spark, d):
    """The last event at or before each user's noon: both sides in one window, so no range join and one shuffle."""
    e = load(spark, d, "events", "event_id", "user_id", "ts").select("user_id", epoch("ts").alias("e"), "event_id")
    q = e.select("user_id", (F.floor(F.col("e") / 86400) * 86400 + 43200).cast("double").alias("e")).distinct()
    both = e.select("user_id", "e", "event_id", F.lit(0).alias("ask")).unionByName(q.select("user_id", "e", F.lit(None).cast("long").alias("event_id"), F.lit(1).alias("ask")))
    w = Window.partitionBy("user_id").orderBy("e", "ask", "event_id")
    found = both.withColumn("last", F.last("event_id", ignorenulls=True).over(w)).where("ask = 1")
    return found.select("user_id", F.col("e").cast("long").alias("at"), F.col("last").alias("event_id"))


@query("x_join_theta", "SELECT a.r_name AS a, b.r_name AS b FROM region a JOIN region b ON a.r_name < b.r_name")
def x_join_theta(spark, d):
    r = load(spark, d, "region", "r_name")
    return r.select(F.col("r_name").alias("a")).join(r.select(F.col("r_name").alias("b")), F.col("a") < F.col("b"))  # five rows


@query("x_agg_basic", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS q, round(avg(l_extendedprice), 4) AS p, min(l_discount + 0.0) AS lo, max(l_tax + 0.0) AS hi, count(*) FILTER (WHERE l_quantity > 25) AS n_big, bool_and(l_quantity > 0) AS positive, round(stddev_pop(l_quantity), 6) AS sd FROM lineitem GROUP BY 1, 2")
def x_agg_basic(spark, d):
    li = load(spark, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    return li.groupBy("l_returnflag", "l_linestatus").agg(
        F.round(F.sum("l_quantity"), 2).alias("q"), F.round(F.avg("l_extendedprice"), 4).alias("p"), (F.min(F.col("l_discount") + 0.0)).alias("lo"), F.max(F.col("l_tax") + 0.0).alias("hi"),
        F.count_if(F.col("l_quantity") > 25).alias("n_big"), F.bool_and(F.col("l_quantity") > 0).alias("positive"), F.round(F.stddev_pop("l_quantity"), 6).alias("sd"))


@query("x_agg_collect", "SELECT o_custkey, string_agg(o_orderkey::VARCHAR, ',' ORDER BY o_orderkey) AS keys, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest FROM orders GROUP BY 1")
def x_agg_collect(spark, d):
    g = load(spark, d, "orders", "o_custkey", "o_orderkey", "o_totalprice").groupBy("o_custkey")
    return g.agg(F.array_join(F.array_sort(F.collect_list("o_orderkey")).cast("array<string>"), ",").alias("keys"), F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"))


@query("x_agg_distinct", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS n_suppliers, count(DISTINCT l_partkey) AS n_parts FROM lineitem GROUP BY 1")
def x_agg_distinct(spark, d):
    g = load(spark, d, "lineitem", "l_returnflag", "l_suppkey", "l_partkey").groupBy("l_returnflag")
    return g.agg(F.count_distinct("l_suppkey").alias("n_suppliers"), F.count_distinct("l_partkey").alias("n_parts"))


@query("x_percentile", "SELECT c_mktsegment, round(quantile_cont(c_acctbal, 0.5), 4) AS median, round(quantile_cont(c_acctbal, 0.9), 4) AS p90 FROM customer GROUP BY 1")
def x_percentile(spark, d):
    g = load(spark, d, "customer", "c_mktsegment", "c_acctbal").groupBy("c_mktsegment")
    return g.agg(F.round(F.percentile("c_acctbal", 0.5), 4).alias("median"), F.round(F.percentile("c_acctbal", 0.9), 4).alias("p90"))


@query("x_sketches")
def x_sketches(spark, d):
    """Approximate measures beside the exact ones: HLL and quantiles."""
    return load(spark, d, "lineitem", "l_partkey", "l_quantity", "l_extendedprice").agg(
        F.count_distinct("l_partkey").alias("exact"), F.approx_count_distinct("l_partkey", 0.02).alias("hll"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 14)).alias("hll_sketch"),
        F.percentile("l_extendedprice", 0.5).alias("median"), F.percentile_approx("l_extendedprice", 0.5, 10000).alias("approx_median"))


_REV = "FROM customer JOIN orders ON c_custkey = o_custkey"


def _revenue(spark, d):
    c, o = load(spark, d, "customer", "c_custkey", "c_mktsegment"), load(spark, d, "orders", "o_custkey", "o_orderstatus", "o_totalprice")
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"))


@query("x_rollup", f"SELECT c_mktsegment, o_orderstatus, count(*) AS n, round(sum(o_totalprice), 2) AS revenue {_REV} GROUP BY ROLLUP (c_mktsegment, o_orderstatus)")
def x_rollup(spark, d):
    return _revenue(spark, d).rollup("c_mktsegment", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("revenue"))


@query("x_cube", f"SELECT c_mktsegment, o_orderstatus, count(*) AS n {_REV} GROUP BY CUBE (c_mktsegment, o_orderstatus)")
def x_cube(spark, d):
    return _revenue(spark, d).cube("c_mktsegment", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@query("x_pivot", f"SELECT c_mktsegment, count(*) FILTER (WHERE o_orderstatus = 'F') AS f, count(*) FILTER (WHERE o_orderstatus = 'O') AS o, count(*) FILTER (WHERE o_orderstatus = 'P') AS p {_REV} GROUP BY 1")
def x_pivot(spark, d):
    p = _revenue(spark, d).groupBy("c_mktsegment").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return p.select("c_mktsegment", *[F.coalesce(F.col(c), F.lit(0)).alias(c.lower()) for c in "FOP"])


_Q = "(PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)"


@query("x_window_rank", f"SELECT c_custkey, row_number() OVER {_Q}::INT AS rn, rank() OVER {_Q}::INT AS rk, dense_rank() OVER {_Q}::INT AS dr, ntile(4) OVER {_Q}::INT AS nt, round(percent_rank() OVER {_Q}, 6) AS pr, round(cume_dist() OVER {_Q}, 6) AS cd FROM customer")
def x_window_rank(spark, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return load(spark, d, "customer", "c_custkey", "c_nationkey", "c_acctbal").select(
        "c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("x_window_analytic", "SELECT o_orderkey, lag(o_orderkey) OVER q AS prev, lead(o_orderkey, 2) OVER q AS next2, first_value(o_orderkey) OVER q AS first, nth_value(o_orderkey, 2) OVER q AS second FROM orders WINDOW q AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def x_window_analytic(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return load(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate").select(
        "o_orderkey", F.lag("o_orderkey").over(w).alias("prev"), F.lead("o_orderkey", 2).over(w).alias("next2"), F.first("o_orderkey").over(w).alias("first"), F.nth_value("o_orderkey", 2).over(w).alias("second"))


@query("x_window_frames", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING), 4) AS near, round(value / sum(value) OVER (PARTITION BY user_id), 6) AS share FROM events")
def x_window_frames(spark, d):
    w = Window.partitionBy("user_id")
    near = w.orderBy("ts", "event_id").rowsBetween(-2, 1)
    return load(spark, d, "events", "event_id", "user_id", "ts", "value").select("event_id", F.round(F.sum("value").over(near), 4).alias("near"), F.round(F.col("value") / F.sum("value").over(w), 6).alias("share"))


@query("x_topk", "(SELECT 'all' AS kind, o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10) UNION ALL SELECT o_orderpriority, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def x_topk(spark, d):
    o = load(spark, d, "orders", "o_orderkey", "o_orderpriority", "o_totalprice")
    top = o.orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select(F.lit("all").alias("kind"), "o_orderkey")
    w = Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    each = o.withColumn("r", F.row_number().over(w)).where("r <= 3").select(F.col("o_orderpriority").alias("kind"), "o_orderkey")
    return top.unionByName(each)


@query("x_setops", "SELECT 'union' AS op, count(*) AS n FROM (SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier) UNION ALL SELECT 'intersect', count(*) FROM (SELECT c_nationkey FROM customer INTERSECT SELECT s_nationkey FROM supplier) UNION ALL SELECT 'except all', count(*) FROM (SELECT c_nationkey FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier)")
def x_setops(spark, d):
    c, s = load(spark, d, "customer", F.col("c_nationkey").alias("k")), load(spark, d, "supplier", F.col("s_nationkey").alias("k"))
    count = lambda df, name: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("op"), "n")
    return count(c.union(s).distinct(), "union").unionByName(count(c.intersect(s), "intersect")).unionByName(count(c.exceptAll(s), "except all"))


@query("x_hash_sample", "SELECT o_orderkey FROM orders WHERE ('0x' || substr(md5('sample|' || o_orderkey), 1, 8))::BIGINT % 20 = 0")
def x_hash_sample(spark, d):
    """A sampling operator: the same rows in any order, engine and number of tasks."""
    from clipflow.sources.standin import hash8

    return load(spark, d, "orders", "o_orderkey").where(hash8(F.lit("sample"), F.col("o_orderkey").cast("string")) % 20 == 0)


@query("x_string", "SELECT p_partkey, lower(p_name) AS l, length(p_name)::INT AS n, md5(p_brand) AS h, replace(p_type, ' ', '_') AS t, levenshtein(p_brand, p_type)::INT AS lv, instr(p_name, 'a')::INT AS at, translate(p_brand, 'abc', 'xyz') AS tr FROM part")
def x_string(spark, d):
    return load(spark, d, "part", "p_partkey", "p_name", "p_brand", "p_type").select(
        "p_partkey", F.lower("p_name").alias("l"), F.length("p_name").alias("n"), F.md5("p_brand").alias("h"), F.regexp_replace("p_type", " ", "_").alias("t"), F.levenshtein("p_brand", "p_type").alias("lv"), F.instr("p_name", "a").alias("at"), F.translate("p_brand", "abc", "xyz").alias("tr"))


@query("x_datetime", "SELECT o_orderkey, year(o_orderdate)::INT AS y, quarter(o_orderdate)::INT AS q, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS days, strftime(o_orderdate::DATE + 30, '%Y-%m-%d') AS due FROM orders")
def x_datetime(spark, d):
    o = load(spark, d, "orders", "o_orderkey", "o_orderdate").withColumn("dt", F.to_date("o_orderdate"))
    return o.select("o_orderkey", F.year("dt").alias("y"), F.quarter("dt").alias("q"), F.date_format(F.trunc("dt", "month"), "yyyy-MM-dd").alias("m"), F.datediff("dt", F.lit("1992-01-01").cast("date")).alias("days"), F.date_format(F.date_add("dt", 30), "yyyy-MM-dd").alias("due"))


@query("x_math", "SELECT c_custkey, round(ln(abs(c_acctbal) + 1), 6) AS l, round(sqrt(abs(c_acctbal)), 6) AS s, greatest(c_acctbal, 0) AS g, floor(c_acctbal / 100)::BIGINT AS f, round(exp(-abs(c_acctbal) / 1000), 6) AS e, round(m + ln(exp(c_acctbal / 1000 - m) + exp(1 - m)), 6) AS lse FROM (SELECT *, greatest(c_acctbal / 1000, 1) AS m FROM customer)")
def x_math(spark, d):
    from clipflow.functions.ctc import logsumexp

    b = F.col("c_acctbal")
    c = load(spark, d, "customer", "c_custkey", "c_acctbal").withColumn("x", F.array(b / 1000, F.lit(1.0)))
    return c.select("c_custkey", F.round(F.log1p(F.abs(b)), 6).alias("l"), F.round(F.sqrt(F.abs(b)), 6).alias("s"), F.greatest(b, F.lit(0.0)).alias("g"), F.floor(b / 100).alias("f"), F.round(F.exp(-F.abs(b) / 1000), 6).alias("e"), F.round(logsumexp("x"), 6).alias("lse"))


@query("x_array", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS norm, len(list_filter(embedding, lambda x: x > 0))::INT AS n_pos, round(CAST(list_max(embedding[1:8]) AS DOUBLE), 6) AS hi FROM embeddings")
def x_array(spark, d):
    e = load(spark, d, "embeddings", "vec_id", "embedding")
    return e.select("vec_id", F.round(F.expr("aggregate(embedding, 0D, (s, x) -> s + cast(x AS double) * cast(x AS double))"), 4).alias("norm"), F.expr("size(filter(embedding, x -> x > 0))").alias("n_pos"), F.round(F.array_max(F.slice("embedding", 1, 8)).cast("double"), 6).alias("hi"))


@query("x_map", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(DISTINCT event_type)::INT AS kinds FROM events GROUP BY 1")
def x_map(spark, d):
    n = load(spark, d, "events", "user_id", "event_type").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))  # a handful of kinds
    return m.select("user_id", F.coalesce(F.element_at("m", "click"), F.lit(0)).alias("clicks"), F.size(F.map_keys("m")).alias("kinds"))


@query("x_json", """SELECT CAST(regexp_extract(props, '"k": ?(-?[0-9]+)', 1) AS INT) AS k, count(*) AS n FROM events GROUP BY 1""")
def x_json(spark, d):
    e = load(spark, d, "events", "props").select(F.from_json("props", "k int").alias("p"))
    return e.groupBy(F.col("p.k").alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("x_html_title", r"SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, regexp_extract(url, '://[^/]*/([a-z]{2})/', 1) AS lang FROM pages")
def x_html_title(spark, d):
    p = load(spark, d, "pages", "page_id", "url", "html")
    return p.select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.regexp_extract("url", "://[^/]*/([a-z]{2})/", 1).alias("lang"))


@query("x_subquery", "SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer) AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def x_subquery(spark, d):
    c = load(spark, d, "customer", "c_custkey", "c_acctbal")
    mean = c.agg(F.avg("c_acctbal").alias("m")).scalar()
    o = load(spark, d, "orders", F.col("o_custkey").alias("c_custkey"))
    return c.where(F.col("c_acctbal") > mean).join(o, "c_custkey", "left_semi").select("c_custkey")


@query("x_recursive", "WITH RECURSIVE r(n, p) AS (SELECT 1, 1::BIGINT UNION ALL SELECT n + 1, p * (n + 1) FROM r WHERE n < 12) SELECT n::INT AS n, p FROM r")
def x_recursive(spark, d):
    return spark.sql("WITH RECURSIVE r(n, p) AS (SELECT 1, 1L UNION ALL SELECT n + 1, p * (n + 1) FROM r WHERE n < 12) SELECT n, p FROM r")
