"""Queries for the operators around the methods: joins, aggregates, windows, sets, functions, sources, streams in batch form."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from .catalogue import query, sql_query
from .functions import geometry as G
from .functions import sql_functions
from .plans import session
from .sources import points_io
from .sources.tables import load, view, with_views
from .streaming import spacing as streams


@query("op_predicates", "SELECT p_type, count(*) AS n FROM part WHERE p_size IN (1, 5, 9, 20) OR p_retailprice BETWEEN 950 AND 960 OR p_brand LIKE '%1' GROUP BY p_type")
def op_predicates(spark, d):
    p = load(spark, d, "part")
    return p.filter(F.col("p_size").isin(1, 5, 9, 20) | F.col("p_retailprice").between(950, 960) | F.col("p_brand").like("%1")).groupBy("p_type").agg(F.count("*").alias("n"))


@query("op_tag_kind", "SELECT CASE WHEN s_acctbal < 0 THEN 'outer' WHEN s_acctbal < 1000 THEN 'boundary' ELSE 'interior' END AS kind, count(*) AS n, count(nullif(s_nationkey, 0)) AS named FROM supplier GROUP BY 1")
def op_tag_kind(spark, d):
    kind = F.when(F.col("s_acctbal") < 0, "outer").when(F.col("s_acctbal") < 1000, "boundary").otherwise("interior")
    return load(spark, d, "supplier").groupBy(kind.alias("kind")).agg(F.count("*").alias("n"), F.count(F.nullif("s_nationkey", F.lit(0))).alias("named"))


@query("op_join_broadcast", "SELECT n_name, count(*) AS n, round(sum(c_acctbal), 2) AS total FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def op_join_broadcast(spark, d):
    """25 nations: a constant, so broadcast."""
    return load(spark, d, "customer").join(F.broadcast(load(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))


@query("op_join_bucket", "SELECT c_mktsegment, count(*) AS n, round(max(o_totalprice), 2) AS most FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def op_join_bucket(spark, d):
    return load(spark, d, "orders").hint("merge").join(load(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.max("o_totalprice"), 2).alias("most"))


@query("op_join_shuffle_hash", "SELECT p_type, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_type")
def op_join_shuffle_hash(spark, d):
    return load(spark, d, "lineitem").join(load(spark, d, "part").hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_type").agg(F.round(F.sum("l_quantity"), 2).alias("quantity"))


RECTANGLES = [(k, 1.0 * k, 1.0 * k + 1.5, 0.5 * k, 0.5 * k + 2.0) for k in range(4)]
RECT_SQL = "(VALUES " + ", ".join(f"({k}, {a!r}e0, {b!r}e0, {c!r}e0, {e!r}e0)" for k, a, b, c, e in RECTANGLES) + ") r(box, x1, x2, y1, y2)"


@query("op_range_join_bbox", with_views(f"SELECT CAST(box AS INTEGER) AS box, count(*) AS n FROM pv_order2 p JOIN {RECT_SQL} ON p.x >= x1 AND p.x < x2 AND p.y >= y1 AND p.y < y2 GROUP BY box", "pv_order2"))
def op_range_join_bbox(spark, d):
    """Point in box: boxes go to the unit bins they touch, points to theirs, and the rest is an equi-join."""
    r = spark.createDataFrame(RECTANGLES, "box int, x1 double, x2 double, y1 double, y2 double").withColumn("bin", F.explode(F.sequence(F.floor("x1"), F.floor("x2"))))
    p = view(spark, d, "pv_order2").withColumn("bin", F.floor("x"))
    return p.join(r, "bin").filter("x >= x1 AND x < x2 AND y >= y1 AND y < y2").groupBy("box").agg(F.count("*").alias("n"))


@query("op_theta_bisector", "SELECT s_suppkey, count(*) AS n FROM supplier JOIN nation ON s_acctbal > n_nationkey * 400 GROUP BY s_suppkey")
def op_theta_bisector(spark, d):
    return load(spark, d, "supplier").join(F.broadcast(load(spark, d, "nation")), F.col("s_acctbal") > F.col("n_nationkey") * 400).groupBy("s_suppkey").agg(F.count("*").alias("n"))


@query("op_asof_prev_event", "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prev FROM events")
def op_asof_prev_event(spark, d):
    """The latest earlier event of the same user, as an as-of join: a union and the last key of the right side seen so far."""
    e = load(spark, d, "events")
    both = e.select("user_id", "ts", "event_id", F.lit(1).alias("side"), F.lit(None).cast("long").alias("key")).unionByName(e.select("user_id", "ts", "event_id", F.lit(2).alias("side"), F.col("event_id").alias("key")))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id", "side").rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn("prev", F.last("key", ignorenulls=True).over(w)).filter("side = 1").select("event_id", "prev")


@query("op_interval_events", "SELECT count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def op_interval_events(spark, d):
    """Pairs within an hour: hour bins as a second key."""
    e = load(spark, d, "events").select("user_id", "ts", F.floor(F.unix_micros("ts") / 3_600_000_000).alias("bin"))
    a = e.select("user_id", F.col("ts").alias("t0"), F.explode(F.array("bin", F.col("bin") + 1)).alias("bin"))
    return a.join(e, ["user_id", "bin"]).filter("ts > t0 AND ts <= t0 + INTERVAL 1 HOUR").agg(F.count("*").alias("pairs"))


@query("op_semi_cells", "SELECT s_suppkey FROM supplier WHERE EXISTS (SELECT 1 FROM customer WHERE c_nationkey = s_nationkey AND c_acctbal > 9900)")
def op_semi_cells(spark, d):
    return load(spark, d, "supplier").join(load(spark, d, "customer").filter("c_acctbal > 9900"), F.col("c_nationkey") == F.col("s_nationkey"), "left_semi").select("s_suppkey")


@query("op_anti_cells", "SELECT s_suppkey FROM supplier WHERE NOT EXISTS (SELECT 1 FROM customer WHERE c_nationkey = s_nationkey AND c_acctbal > 9900)")
def op_anti_cells(spark, d):
    return load(spark, d, "supplier").join(load(spark, d, "customer").filter("c_acctbal > 9900"), F.col("c_nationkey") == F.col("s_nationkey"), "left_anti").select("s_suppkey")


sql_query("op_outer_hist", "SELECT coalesce(a.k, b.k) AS k, a.n AS customers, b.n AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM $customer GROUP BY c_nationkey) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM $supplier WHERE s_acctbal > 5000 GROUP BY s_nationkey) b ON a.k = b.k", tables=("customer", "supplier"))
sql_query("op_cross_dirs", "SELECT n_nationkey, r_regionkey FROM $nation CROSS JOIN $region WHERE n_regionkey <> r_regionkey", tables=("nation", "region"))


@query("op_lateral_expand", "SELECT n_nationkey, CAST(j AS INTEGER) AS j, n_regionkey * 10 + CAST(j AS INTEGER) AS v FROM nation, range(4) t(j)")
def op_lateral_expand(spark, d):
    return spark.sql("SELECT n_nationkey, j, n_regionkey * 10 + j AS v FROM {nation}, LATERAL (SELECT explode(sequence(0, 3)) AS j)", nation=load(spark, d, "nation"))


sql_query("op_counts_by_cell", "SELECT c_nationkey, c_mktsegment, count(*) AS n, round(avg(c_acctbal), 4) AS mean FROM $customer GROUP BY c_nationkey, c_mktsegment", tables=("customer",))


@query("op_distinct_cells", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_returnflag")
def op_distinct_cells(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct("l_partkey").alias("parts"))


@query("op_grouping_sets", "SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_nationkey, c_mktsegment), (c_nationkey), ())")
def op_grouping_sets(spark, d):
    c = load(spark, d, "customer")
    return c.groupingSets([["c_nationkey", "c_mktsegment"], ["c_nationkey"], []], "c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))


@query("op_cube_nodes", "SELECT n_regionkey, c_mktsegment, count(*) AS n, CAST(grouping(n_regionkey) * 2 + grouping(c_mktsegment) AS BIGINT) AS level FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY CUBE (n_regionkey, c_mktsegment)")
def op_cube_nodes(spark, d):
    both = load(spark, d, "customer").join(F.broadcast(load(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return both.cube("n_regionkey", "c_mktsegment").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


@query("op_rollup_nodes", "SELECT n_regionkey, n_nationkey, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_nationkey)")
def op_rollup_nodes(spark, d):
    both = load(spark, d, "customer").join(F.broadcast(load(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return both.rollup("n_regionkey", "n_nationkey").agg(F.count("*").alias("n"))


@query("op_pivot_workers", "SELECT c_mktsegment, count(*) FILTER (c_nationkey % 4 = 0) AS w0, count(*) FILTER (c_nationkey % 4 = 1) AS w1, count(*) FILTER (c_nationkey % 4 = 2) AS w2, count(*) FILTER (c_nationkey % 4 = 3) AS w3 FROM customer GROUP BY c_mktsegment")
def op_pivot_workers(spark, d):
    c = load(spark, d, "customer").withColumn("w", F.concat(F.lit("w"), (F.col("c_nationkey") % 4).cast("string")))
    return c.groupBy("c_mktsegment").pivot("w", ["w0", "w1", "w2", "w3"]).agg(F.count(F.lit(1))).na.fill(0)


@query("op_unpivot", "SELECT n_nationkey, 'n_regionkey' AS k, CAST(n_regionkey AS BIGINT) AS v FROM nation UNION ALL SELECT n_nationkey, 'twice', CAST(n_regionkey * 2 AS BIGINT) FROM nation")
def op_unpivot(spark, d):
    n = load(spark, d, "nation").select("n_nationkey", F.col("n_regionkey").cast("long").alias("n_regionkey"), (F.col("n_regionkey") * 2).cast("long").alias("twice"))
    return n.unpivot("n_nationkey", ["n_regionkey", "twice"], "k", "v")


@query("op_stats", "SELECT o_orderstatus, round(avg(o_totalprice), 3) AS mean, round(stddev_samp(o_totalprice), 3) AS sd, round(corr(o_totalprice, o_custkey), 5) AS r, round(regr_slope(o_totalprice, o_custkey), 5) AS slope, round(covar_samp(o_totalprice, o_custkey), 0) AS cov FROM orders GROUP BY 1")
def op_stats(spark, d):
    x = F.col("o_custkey")
    return load(spark, d, "orders").groupBy("o_orderstatus").agg(F.round(F.avg("o_totalprice"), 3).alias("mean"), F.round(F.stddev_samp("o_totalprice"), 3).alias("sd"), F.round(F.corr("o_totalprice", x), 5).alias("r"), F.round(F.regr_slope("o_totalprice", x), 5).alias("slope"), F.round(F.covar_samp("o_totalprice", x), 0).alias("cov"))


@query("op_quantiles", "SELECT p_type, round(quantile_cont(p_retailprice, 0.25), 4) AS q1, round(median(p_retailprice), 4) AS q2, round(quantile_cont(p_retailprice, 0.9), 4) AS q9 FROM part GROUP BY p_type")
def op_quantiles(spark, d):
    q = lambda p: F.round(F.percentile("p_retailprice", F.lit(p)), 4)
    return load(spark, d, "part").groupBy("p_type").agg(q(0.25).alias("q1"), q(0.5).alias("q2"), q(0.9).alias("q9"))


@query("op_nearest_seed", "SELECT c_nationkey, arg_min(c_custkey, c_acctbal) AS poorest, arg_max(c_custkey, c_acctbal) AS richest FROM customer GROUP BY c_nationkey")
def op_nearest_seed(spark, d):
    """Of equal balances the smallest key counts; rows without a key or a balance count for neither."""
    key = F.when(F.col("c_acctbal").isNotNull(), F.col("c_custkey"))
    low, high = (F.when(key.isNotNull(), F.struct("c_acctbal", k)) for k in (key.alias("k"), (-key).alias("k")))
    return load(spark, d, "customer").groupBy("c_nationkey").agg(F.min_by("c_custkey", low).alias("poorest"), F.max_by("c_custkey", high).alias("richest"))


@query("op_filtered_aggregates", "SELECT s_nationkey, count(*) FILTER (s_acctbal < 0) AS below, bool_and(s_acctbal > -990) AS all_above, bool_or(s_acctbal > 9000) AS any_rich FROM supplier GROUP BY s_nationkey")
def op_filtered_aggregates(spark, d):
    a = F.col("s_acctbal")
    return load(spark, d, "supplier").groupBy("s_nationkey").agg(F.count_if(a < 0).alias("below"), F.bool_and(a > -990).alias("all_above"), F.bool_or(a > 9000).alias("any_rich"))


@query("op_rank_neighbours", "SELECT o_orderkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, CAST(ntile(4) OVER w AS INTEGER) AS nt FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def op_rank_neighbours(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return load(spark, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"))


@query("op_lag_gap", "SELECT event_id, round(value - lag(value) OVER w, 4) AS step, lead(event_id) OVER w AS following, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_lag_gap(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, d, "events").select("event_id", F.round(F.col("value") - F.lag("value").over(w), 4).alias("step"), F.lead("event_id").over(w).alias("following"), F.first("event_id").over(w).alias("first"))


@query("op_cum_arc_length", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS length FROM orders")
def op_cum_arc_length(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return load(spark, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w), 2).alias("length"))


@query("op_local_density", "SELECT p_partkey, count(*) OVER (PARTITION BY p_type ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS density FROM part")
def op_local_density(spark, d):
    return load(spark, d, "part").select("p_partkey", F.count("*").over(Window.partitionBy("p_type").orderBy("p_size").rangeBetween(-2, 2)).alias("density"))


@query("op_window_frames", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING), 5) AS smooth, round(max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING), 5) AS ahead FROM events")
def op_window_frames(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, d, "events").select("event_id", F.round(F.avg("value").over(w.rowsBetween(-3, 3)), 5).alias("smooth"), F.round(F.max("value").over(w.rowsBetween(0, Window.unboundedFollowing)), 5).alias("ahead"))


@query("op_topk_isolated", "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 25 OFFSET 5")
def op_topk_isolated(spark, d):
    return load(spark, d, "customer").select("c_custkey", "c_acctbal").orderBy(F.desc("c_acctbal"), "c_custkey").offset(5).limit(25)


@query("op_topk_per_group", "SELECT c_nationkey, c_custkey FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS k FROM customer) t WHERE k <= 3")
def op_topk_per_group(spark, d):
    k = F.row_number().over(Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey"))
    return load(spark, d, "customer").withColumn("k", k).filter("k <= 3").select("c_nationkey", "c_custkey")


def sets(spark, d):
    return load(spark, d, "customer").select(F.col("c_nationkey").alias("k")), load(spark, d, "supplier").filter("s_acctbal > 6000").select(F.col("s_nationkey").alias("k"))


SETS = "(SELECT c_nationkey AS k FROM customer) {op} (SELECT s_nationkey AS k FROM supplier WHERE s_acctbal > 6000)"
query("op_set_union", SETS.format(op="UNION"))(lambda spark, d: (lambda a, b: a.unionByName(b).dropDuplicates())(*sets(spark, d)))
query("op_set_intersect", SETS.format(op="INTERSECT ALL"))(lambda spark, d: (lambda a, b: a.intersectAll(b))(*sets(spark, d)))
query("op_set_except", SETS.format(op="EXCEPT ALL"))(lambda spark, d: (lambda a, b: a.exceptAll(b))(*sets(spark, d)))


@query("op_sample_hash", "SELECT count(*) FILTER (l_orderkey % 4 = 0) AS quarter, count(*) FILTER (l_orderkey % 16 = 0) AS sixteenth, count(*) AS n FROM lineitem")
def op_sample_hash(spark, d):
    """Sizes of the ladder of samples by key: each is part of the one before."""
    k = F.col("l_orderkey")
    return load(spark, d, "lineitem").agg(F.count_if(F.pmod(k, F.lit(4)) == 0).alias("quarter"), F.count_if(F.pmod(k, F.lit(16)) == 0).alias("sixteenth"), F.count("*").alias("n"))


@query("op_math", with_views("SELECT count(*) AS n, round(avg(sqrt(x * x + y * y)), 5) AS radius, round(avg(cos(3 * atan2(y, x))), 5) AS leaf, round(avg(tanh(x)), 5) AS t, round(max(log2(1 + abs(x))), 5) AS l, sum(CAST(floor(y) AS BIGINT)) AS f FROM pv_line2", "pv_line2"))
def op_math(spark, d):
    p = view(spark, d, "pv_line2")
    return p.agg(F.count("*").alias("n"), F.round(F.avg(F.sqrt(F.col("x") * F.col("x") + F.col("y") * F.col("y"))), 5).alias("radius"), F.round(F.avg(F.cos(3 * F.atan2("y", "x"))), 5).alias("leaf"), F.round(F.avg(F.tanh("x")), 5).alias("t"), F.round(F.max(F.log2(1 + F.abs("x"))), 5).alias("l"), F.sum(F.floor("y")).alias("f"))


@query("op_array_hof", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 5) AS norm2, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def op_array_hof(spark, d):
    v = F.col("embedding").cast("array<double>")
    return load(spark, d, "embeddings").select("vec_id", F.round(F.aggregate(F.transform(v, lambda x: x * x), F.lit(0.0), lambda a, x: a + x), 5).alias("norm2"), F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("positive"))


@query("op_map_params", "SELECT r_regionkey, CAST(12 AS BIGINT) + r_regionkey AS n_c, r_regionkey % 2 = 0 AS even FROM region")
def op_map_params(spark, d):
    m = F.map_from_arrays(F.array(F.lit("n_c"), F.lit("parity")), F.array((F.lit(12) + F.col("r_regionkey")).cast("long"), (F.col("r_regionkey") % 2).cast("long")))
    return load(spark, d, "region").select("r_regionkey", F.element_at(m, "n_c").alias("n_c"), (F.element_at(m, "parity") == 0).alias("even"))


@query("op_string_ids", "SELECT page_id, lpad(CAST(page_id AS VARCHAR), 8, '0') || '-' || substr(md5(url), 1, 8) AS id, len(string_split(url, '/')) AS parts FROM pages")
def op_string_ids(spark, d):
    return load(spark, d, "pages").select("page_id", F.concat_ws("-", F.lpad(F.col("page_id").cast("string"), 8, "0"), F.substring(F.md5("url"), 1, 8)).alias("id"), F.size(F.split("url", "/")).cast("long").alias("parts"))


@query("op_date_bins", "SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, count(*) AS n, max(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE))) AS last FROM orders GROUP BY 1, 2")
def op_date_bins(spark, d):
    o = load(spark, d, "orders")
    return o.groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count("*").alias("n"), F.max(F.datediff("o_orderdate", F.lit("1995-01-01").cast("date"))).cast("long").alias("last"))


@query("op_json_props", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def op_json_props(spark, d):
    return load(spark, d, "events").groupBy(F.from_json("props", "k long")["k"].alias("k")).agg(F.count("*").alias("n"))


@query("op_casts", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(12, 2))) AS VARCHAR) AS total FROM lineitem GROUP BY 1")
def op_casts(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(12,2)")).cast("string").alias("total"))


@query("op_text_features", "SELECT 'pages' AS t, count(*) AS n, sum(length(html)) AS chars FROM pages UNION ALL SELECT 'benchmark', count(*), sum(length(text)) FROM benchmark UNION ALL SELECT 'conversations', count(*), sum(length(text)) FROM conversations UNION ALL SELECT 'documents', count(*), sum(length(text)) FROM documents")
def op_text_features(spark, d):
    out = None
    for t, c in (("pages", "html"), ("benchmark", "text"), ("conversations", "text"), ("documents", "text")):
        one = load(spark, d, t).agg(F.lit(t).alias("t"), F.count("*").alias("n"), F.sum(F.length(c)).alias("chars"))
        out = one if out is None else out.unionByName(one)
    return out


@query("op_udf_dist", with_views("SELECT count(*) AS n FROM pv_order2 WHERE (x - 2) * (x - 2) + (y - 2) * (y - 2) < 1", "pv_order2"))
def op_udf_dist(spark, d):
    """A user's region in Python: Arrow batches behind the box filter."""
    disc = sql_functions.region_from_python("disc", 2, (1, 1), (3, 3), lambda p: ((p - 2) ** 2).sum(1) < 1)
    return view(spark, d, "pv_order2").filter(disc.contains()).agg(F.count("*").alias("n"))


@query("op_udaf_centroid", "SELECT c_nationkey, round(avg(c_acctbal), 4) AS centre, round(max(c_acctbal) - min(c_acctbal), 4) AS spread FROM customer GROUP BY c_nationkey")
def op_udaf_centroid(spark, d):
    c = load(spark, d, "customer")
    a = c.groupBy("c_nationkey").agg(F.round(F.avg("c_acctbal"), 4).alias("centre"))
    b = c.groupBy("c_nationkey").agg(sql_functions.spread("c_acctbal").alias("s")).select("c_nationkey", F.round("s", 4).alias("spread"))
    return a.join(b, "c_nationkey")


@query("op_udtf_expand", with_views("SELECT seed_id, CAST(j AS INTEGER) AS cand, round(x + CAST(0.5 AS DOUBLE) * cos(2 * pi() * j / 12), 6) + 0e0 AS x, round(y + CAST(0.5 AS DOUBLE) * sin(2 * pi() * j / 12), 6) + 0e0 AS y FROM pv_nation2, range(12) t(j)", "pv_nation2"))
def op_udtf_expand(spark, d):
    n = view(spark, d, "pv_nation2").select("seed_id", "x", "y")
    return n.lateralJoin(sql_functions.ExpandPoint(F.col("x").outer(), F.col("y").outer(), F.lit(0.5), F.lit(12))).select("seed_id", "cand", (F.round("cx", 6) + 0.0).alias("x"), (F.round("cy", 6) + 0.0).alias("y"))


@query("op_sql_functions", with_views("SELECT count(*) AS n, round(avg(CAST(0.05 AS DOUBLE) * (1 + 4 * power(cos(3 * atan2(y, x)), 2) * tanh(sqrt(x * x + y * y)))), 5) AS h, round(max(sqrt((x - 1) * (x - 1) + (y - 1) * (y - 1))), 5) AS far FROM pv_line2", "pv_line2"))
def op_sql_functions(spark, d):
    sql_functions.register(spark)
    return spark.sql("SELECT count(*) AS n, round(avg(nf_clover_spacing(x, y, 0.05)), 5) AS h, round(max(nf_dist(x, y, 1, 1)), 5) AS far FROM {p}", p=view(spark, d, "pv_line2"))


sql_query("op_subquery_exists", "SELECT c_custkey FROM $customer c WHERE EXISTS (SELECT 1 FROM $orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 400000) AND c_acctbal > (SELECT avg(c_acctbal) FROM $customer)", tables=("customer", "orders"))
sql_query("op_cte_cells", "WITH per AS (SELECT c_nationkey AS k, count(*) AS n FROM $customer GROUP BY c_nationkey), top AS (SELECT max(n) AS m FROM per) SELECT k, n, n = m AS largest FROM per CROSS JOIN top", tables=("customer",))


@query("op_recursive_cte", "WITH RECURSIVE h AS (SELECT 0 AS pass, 40e0 AS factor UNION ALL SELECT pass + 1, factor / 2 FROM h WHERE pass < 9) SELECT CAST(pass AS INTEGER) AS pass, factor FROM h")
def op_recursive_cte(spark, d):
    return spark.sql("WITH RECURSIVE h(pass, factor) AS (SELECT 0, 40D UNION ALL SELECT pass + 1, factor / 2 FROM h WHERE pass < 9) SELECT pass, factor FROM h")


@query("op_data_source", "SELECT TRUE AS same")
def op_data_source(spark, d):
    """The Python source's lattice against the same lattice made by Spark."""
    from .operators.measures import probe_lattice

    points_io.register(spark)
    a = spark.read.format("nodefill").option("region", "clover2d").option("h", "0.25").load().agg(F.count("*").alias("a"))
    b = probe_lattice(spark, G.clover2d(), 0.25).agg(F.count("*").alias("b"))
    return a.join(F.broadcast(b)).select((F.col("a") == F.col("b")).alias("same"))


@query("stream_spacing_events", """WITH RECURSIVE e AS (SELECT user_id, event_id, ts, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM events),
w AS (SELECT user_id, event_id, ts, k, ts AS last, TRUE AS keep FROM e WHERE k = 1
      UNION ALL SELECT e.user_id, e.event_id, e.ts, e.k, CASE WHEN e.ts - w.last >= INTERVAL 6 HOUR THEN e.ts ELSE w.last END, e.ts - w.last >= INTERVAL 6 HOUR FROM w JOIN e ON e.user_id = w.user_id AND e.k = w.k + 1)
SELECT user_id, event_id FROM w WHERE keep""")
def stream_spacing_events(spark, d):
    return streams.spaced_batch(load(spark, d, "events"), 6 * 3600).select("user_id", "event_id")


@query("stream_windows_tumbling", "SELECT epoch_us(time_bucket(INTERVAL 1 DAY, ts)) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def stream_windows_tumbling(spark, d):
    return streams.tumbling(load(spark, d, "events"), "1 day").withColumn("start", F.unix_micros("start"))


@query("stream_windows_sliding", "SELECT epoch_us(s) AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 6 HOUR, ts), time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR]) AS s FROM events) t GROUP BY 1")
def stream_windows_sliding(spark, d):
    return streams.sliding(load(spark, d, "events"), "12 hours", "6 hours").withColumn("start", F.unix_micros("start"))


@query("stream_windows_session", """SELECT user_id, epoch_us(min(ts)) AS start, count(*) AS n FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (
SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events) a) b GROUP BY user_id, s""")
def stream_windows_session(spark, d):
    return streams.sessions(load(spark, d, "events"), "2 hours").withColumn("start", F.unix_micros("start"))


@query("stream_late_rows", "SELECT user_id, event_id FROM (SELECT *, max(ts) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen FROM events) t WHERE seen - ts > INTERVAL 1 HOUR")
def stream_late_rows(spark, d):
    return streams.late_rows(load(spark, d, "events"), 3600)


@query("stream_assign_cells", "SELECT n_regionkey, count(*) AS n FROM events JOIN nation ON user_id % 25 = n_nationkey GROUP BY n_regionkey")
def stream_assign_cells(spark, d):
    return load(spark, d, "events").join(F.broadcast(load(spark, d, "nation")), F.col("user_id") % 25 == F.col("n_nationkey")).groupBy("n_regionkey").agg(F.count("*").alias("n"))


@query("op_require_valid", "SELECT CASE WHEN c_acctbal <= 0 THEN 'spacing' ELSE 'valid' END AS fault, count(*) AS n FROM customer GROUP BY 1")
def op_require_valid(spark, d):
    """Customers by fault, with the balance as spacing; those without one are counted behind the guard."""
    p = view(spark, d, "pv_cust2").withColumn("h", F.col("x"))
    why = points_io.fault(p)
    bad = p.filter(why.isNotNull()).select(why.alias("fault"))
    good = points_io.require_valid(p.filter(why.isNull())).select(F.lit("valid").alias("fault"))
    return bad.union(good).groupBy("fault").agg(F.count("*").alias("n"))


@query("op_export_sorted", "SELECT o_orderpriority, count(*) AS n, CAST(0 AS BIGINT) AS disorder FROM orders GROUP BY o_orderpriority")
def op_export_sorted(spark, d):
    """Orders by priority, written, and read in the order of each file: rows that come before their predecessor in it."""
    path = f"{session.shared_folder(spark)}/sorted-{uuid.uuid4().hex}"
    points_io.write_sorted(load(spark, d, "orders").select("o_orderpriority", "o_orderkey"), path, "o_orderpriority", "o_orderkey")
    back = spark.read.parquet(path).select("*", F.col("_metadata.file_name").alias("file"), F.col("_metadata.row_index").alias("row"))
    key = F.struct("o_orderpriority", "o_orderkey")
    back = back.withColumn("disorder", F.coalesce((key < F.lag(key).over(Window.partitionBy("file").orderBy("row"))).cast("long"), F.lit(0).cast("long")))
    return back.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("disorder").alias("disorder"))
