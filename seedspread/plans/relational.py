"""The relational surface a user of the methods needs, each with the SQL of the same rows.

Where one text is valid for both engines it is written once and run through ``spark.sql`` on the given
tables; the rest use the DataFrame API beside their SQL.
"""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from seedspread.runtime import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def run_sql(spark: SparkSession, sf_dir: str, sql: str, **views: DataFrame) -> DataFrame:
    """SQL over the given tables without registering names in the session."""
    names = {t for t in TABLES if re.search(rf"\{{{t}\}}", sql)}
    return spark.sql(sql, **{t: table(spark, sf_dir, t) for t in names}, **views)


def shared(name: str, sql: str) -> None:
    """A query whose text both engines run; table names stand in braces."""
    QUERIES[name] = lambda spark, sf: run_sql(spark, sf, sql)
    ORACLES[name] = re.sub(r"\{(\w+)\}", r"\1", sql)


def register(name: str, sql: str):
    def add(query):
        QUERIES[name], ORACLES[name] = query, sql
        return query
    return add


shared("scan_lineitem_pruned", "SELECT l_orderkey, l_partkey FROM {lineitem} WHERE l_suppkey = 3")
shared("scan_pushdown_dates", "SELECT o_orderkey, o_custkey FROM {orders} WHERE o_orderdate >= TIMESTAMP '1997-01-01 00:00:00' AND o_orderdate < TIMESTAMP '1997-03-01 00:00:00'")
shared("filter_compound", "SELECT c_custkey, c_nationkey FROM {customer} WHERE (c_acctbal BETWEEN 0 AND 5000 AND c_mktsegment LIKE 'B%') OR c_nationkey IN (1, 2)")
shared("case_bucket", "SELECT CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'mid' ELSE 'high' END AS bucket, count(*) AS n FROM {customer} GROUP BY 1")
shared("join_orders_lineitem", "SELECT o_custkey, count(*) AS n FROM {orders} JOIN {lineitem} ON o_orderkey = l_orderkey GROUP BY o_custkey")
shared("join_range_prefix", "SELECT a.n_nationkey AS i, CAST(sum(b.n_regionkey) AS BIGINT) AS upto FROM {nation} a JOIN {nation} b ON b.n_nationkey <= a.n_nationkey GROUP BY a.n_nationkey")
shared("join_semi_active", "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey)")
shared("join_anti_peel", "SELECT c_custkey FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_orderdate >= TIMESTAMP '1997-01-01 00:00:00')")
shared("cross_grid", "SELECT n_nationkey AS seed, r_regionkey AS point FROM {nation} CROSS JOIN {region}")
shared("agg_degree", "SELECT l_partkey AS v, count(DISTINCT l_suppkey) AS deg, min(l_suppkey) AS low, max(l_suppkey) AS high FROM {lineitem} GROUP BY l_partkey")
shared("agg_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM {lineitem}")
shared("agg_having", "SELECT l_partkey, count(*) AS n FROM {lineitem} GROUP BY l_partkey HAVING count(*) > 35")
shared("agg_cube", "SELECT event_type, user_id % 3 AS grp, count(*) AS n FROM {events} GROUP BY CUBE (event_type, user_id % 3)")
shared("agg_rollup", "SELECT event_type, user_id % 3 AS grp, count(*) AS n FROM {events} GROUP BY ROLLUP (event_type, user_id % 3)")
shared("agg_grouping_sets", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM {customer} GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")
shared("win_rank", "SELECT c_custkey, CAST(rank() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC) AS BIGINT) AS r, CAST(dense_rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS BIGINT) AS dr, CAST(ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS BIGINT) AS q FROM {customer}")
shared("win_percent", "SELECT c_custkey, round(percent_rank() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal), 9) AS pr, round(cume_dist() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal), 9) AS cd FROM {customer}")
shared("win_running_sum", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto FROM {orders}")
shared("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY user_id RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near FROM {events}")
shared("win_lag_lead", "SELECT o_orderkey, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS before, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS after, first_value(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS first FROM {orders}")
shared("topk_degree", "SELECT l_partkey AS v, count(*) AS deg FROM {lineitem} GROUP BY l_partkey ORDER BY deg DESC, v LIMIT 10")
shared("topk_per_group", "SELECT c_nationkey, c_custkey FROM (SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS o FROM {customer}) WHERE o <= 3")
shared("set_union", "SELECT c_nationkey AS k FROM {customer} UNION SELECT s_nationkey FROM {supplier}")
shared("set_union_all", "SELECT k, count(*) AS n FROM (SELECT c_nationkey AS k FROM {customer} UNION ALL SELECT s_nationkey FROM {supplier}) GROUP BY k")
shared("set_intersect", "SELECT l_partkey AS k FROM {lineitem} WHERE l_suppkey = 1 INTERSECT SELECT l_partkey FROM {lineitem} WHERE l_suppkey = 2")
shared("set_except", "SELECT l_partkey AS k FROM {lineitem} WHERE l_suppkey = 1 EXCEPT SELECT l_partkey FROM {lineitem} WHERE l_suppkey = 2")
shared("date_extract", "SELECT CAST(EXTRACT(YEAR FROM o_orderdate) AS BIGINT) AS y, CAST(EXTRACT(MONTH FROM o_orderdate) AS BIGINT) AS m, count(*) AS n FROM {orders} GROUP BY 1, 2")
shared("date_hour_bucket", "SELECT date_trunc('hour', ts) AS hour, count(*) AS n FROM {events} GROUP BY 1")
shared("subquery_scalar", "SELECT c_custkey FROM {customer} WHERE c_acctbal > (SELECT avg(c_acctbal) FROM {customer})")
shared("subquery_correlated", "SELECT o_orderkey FROM {orders} o WHERE o_orderdate = (SELECT max(o_orderdate) FROM {orders} i WHERE i.o_custkey = o.o_custkey)")
shared("subquery_in", "SELECT s_suppkey FROM {supplier} WHERE s_nationkey IN (SELECT n_nationkey FROM {nation} WHERE n_regionkey = 1)")
shared("cte_reach_bounded", """WITH RECURSIVE link AS (SELECT n_nationkey * 4 + 2 AS a, n_regionkey * 4 + 3 AS b FROM {nation} UNION ALL SELECT n_regionkey * 4 + 3, n_nationkey * 4 + 2 FROM {nation}),
r(v, k) AS (SELECT 2, 0 UNION ALL SELECT b, k + 1 FROM r JOIN link ON a = v WHERE k < 3) SELECT DISTINCT v, k FROM r""")


@register("math_poisson_cdf", "SELECT k, CASE WHEN k < 0 THEN 0 ELSE round(list_sum([exp(j * ln(5.0) - 5.0 - lgamma(j + 1)) FOR j IN range(0, k + 1)]), 9) END AS p FROM (SELECT DISTINCT r_regionkey AS k FROM region) t")
def math_poisson_cdf(spark, sf):
    """Cumulative at every region key: the terms of keys that are not in the table are summed too."""
    from seedspread.functions.sql import poisson_cdf

    levels = table(spark, sf, "region").select(F.col("r_regionkey").alias("k")).distinct()
    return levels.select("k", F.round(poisson_cdf(F.col("k"), 5.0), 9).alias("p"))


@register("join_nation_region_broadcast", "SELECT n_nationkey, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def join_nation_region_broadcast(spark, sf):
    """Region has five rows by definition, so the hint needs no check."""
    nation, region = table(spark, sf, "nation"), table(spark, sf, "region")
    return nation.join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")


@register("join_theta_price", "SELECT a.p_partkey AS low, count(*) AS dearer FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_type = b.p_type AND a.p_retailprice < b.p_retailprice GROUP BY a.p_partkey")
def join_theta_price(spark, sf):
    """Prices of a group are counted once and scanned from the dearest down, so no pair of parts is made."""
    group, price = ["p_brand", "p_type"], "p_retailprice"
    parts = table(spark, sf, "part").select(F.col("p_partkey").alias("low"), *group, price).na.drop(subset=[*group, price])
    above = Window.partitionBy(*group).orderBy(F.col(price).desc()).rowsBetween(Window.unboundedPreceding, -1)
    dearer = parts.groupBy(*group, price).agg(F.count("*").alias("n")).withColumn("dearer", F.sum("n").over(above)).filter("dearer > 0")
    return parts.join(dearer, [*group, price]).groupBy("low").agg(F.sum("dearer").alias("dearer"))


@register("join_part_supp", "SELECT DISTINCT l_partkey, s_nationkey FROM lineitem JOIN supplier ON l_suppkey = s_suppkey")
def join_part_supp(spark, sf):
    """Both sides shuffled on the key and hashed."""
    return table(spark, sf, "lineitem").join(table(spark, sf, "supplier").hint("shuffle_hash"), F.col("l_suppkey") == F.col("s_suppkey")).select("l_partkey", "s_nationkey").distinct()


@register("join_left_missing", "SELECT c_custkey, coalesce(n, 0)::BIGINT AS n FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) ON c_custkey = o_custkey")
def join_left_missing(spark, sf):
    """A sparse read: absent keys are 0."""
    counts = table(spark, sf, "orders").groupBy("o_custkey").agg(F.count("*").alias("n"))
    return table(spark, sf, "customer").join(counts, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n"))


@register("join_full_vectors", "SELECT coalesce(a.k, b.k)::BIGINT AS k, (coalesce(x, 0) - coalesce(y, 0))::BIGINT AS gap FROM (SELECT c_nationkey AS k, count(*) AS x FROM customer WHERE c_nationkey < 15 GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS y FROM supplier WHERE s_nationkey > 8 GROUP BY 1) b ON a.k = b.k")
def join_full_vectors(spark, sf):
    a = table(spark, sf, "customer").filter("c_nationkey < 15").groupBy(F.col("c_nationkey").cast("long").alias("k")).agg(F.count("*").alias("x"))
    b = table(spark, sf, "supplier").filter("s_nationkey > 8").groupBy(F.col("s_nationkey").cast("long").alias("k")).agg(F.count("*").alias("y"))
    return a.join(b, "k", "full").select("k", (F.coalesce("x", F.lit(0)) - F.coalesce("y", F.lit(0))).alias("gap"))


@register("asof_event_prev", "SELECT a.event_id, b.event_id AS prev FROM events a ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) b ON a.user_id = b.user_id AND a.ts > b.ts")
def asof_event_prev(spark, sf):
    """For every event the user's last purchase before it: one window per user, no join."""
    events = table(spark, sf, "events").select("event_id", "user_id", "ts", "event_type")
    marked = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    before = F.max(F.when(marked.isNotNull(), F.struct(F.col("ts"), marked.alias("m")))).over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(Window.unboundedPreceding, -1))
    return events.select("event_id", before["m"].alias("prev"))


@register("interval_events_1h", "SELECT a.event_id, count(b.event_id)::BIGINT AS near FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY a.event_id")
def interval_events_1h(spark, sf):
    """Range join made an equi-join on hour buckets: each event looks in its own and the next bucket."""
    micros = F.unix_micros(F.col("ts").cast("timestamp"))
    events = table(spark, sf, "events").select("event_id", "user_id", micros.alias("at"), F.floor(micros / 3_600_000_000).alias("hour"))
    ahead = events.select(F.col("event_id").alias("o"), "user_id", F.col("at").alias("oat"), "hour")
    looks = events.withColumn("hour", F.explode(F.array(F.col("hour"), F.col("hour") + 1)))
    hits = looks.join(ahead, ["user_id", "hour"]).filter("oat > at and oat <= at + 3600000000").groupBy("event_id").agg(F.count("*").alias("near"))
    return events.join(hits, "event_id", "left").select("event_id", F.coalesce("near", F.lit(0)).alias("near"))


@register("agg_pivot_event", "SELECT user_id, count(*) FILTER (event_type = 'click')::BIGINT AS click, count(*) FILTER (event_type = 'view')::BIGINT AS view FROM events GROUP BY user_id")
def agg_pivot_event(spark, sf):
    wide = table(spark, sf, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1)))
    return wide.na.fill(0, ["click", "view"])


@register("agg_min_by", "SELECT c_nationkey, min_by(c_custkey, c_acctbal) AS poorest, max_by(c_custkey, c_acctbal) AS richest FROM customer GROUP BY c_nationkey")
def agg_min_by(spark, sf):
    """Of equal balances the smallest key is taken, the first one that a reader in key order meets; rows without a key or a balance are no candidates."""
    held = F.col("c_custkey").isNotNull() & F.col("c_acctbal").isNotNull()
    low, high = (F.when(held, F.struct("c_acctbal", (sign * F.col("c_custkey")).alias("k"))) for sign in (1, -1))
    return table(spark, sf, "customer").groupBy("c_nationkey").agg(F.min(low)["k"].alias("poorest"), (-F.max(high)["k"]).alias("richest"))


@register("str_href", "SELECT page_id, path FROM (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS path FROM pages)")
def str_href(spark, sf):
    from seedspread.sources.builders import page_links

    return page_links(spark, sf)


@register("str_lines", "SELECT trim(line, ' ') AS line, count(DISTINCT doc_id)::BIGINT AS docs FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(trim(line, ' ')) >= 20 GROUP BY 1 HAVING count(DISTINCT doc_id) > 1")
def str_lines(spark, sf):
    lines = table(spark, sf, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    lines = lines.select("doc_id", F.trim("line").alias("line"))
    return lines.filter(F.length("line") >= 20).groupBy("line").agg(F.countDistinct("doc_id").alias("docs")).filter("docs > 1")


@register("json_props_k", "SELECT json_extract_string(props, '$.k')::BIGINT AS k, count(*)::BIGINT AS n FROM events GROUP BY 1")
def json_props_k(spark, sf):
    return table(spark, sf, "events").groupBy(F.from_json("props", "k long")["k"].alias("k")).agg(F.count("*").alias("n"))


@register("arr_adjacency", "SELECT l_partkey AS v, string_agg(DISTINCT l_suppkey::VARCHAR, ',' ORDER BY l_suppkey::VARCHAR) AS nbrs FROM lineitem GROUP BY 1")
def arr_adjacency(spark, sf):
    lists = table(spark, sf, "lineitem").groupBy(F.col("l_partkey").alias("v")).agg(F.array_sort(F.collect_set(F.col("l_suppkey").cast("string"))).alias("l"))
    return lists.select("v", F.array_join("l", ",").alias("nbrs"))


@register("arr_common_nbrs", "WITH a AS (SELECT p_brand AS v, list(DISTINCT l_suppkey) AS l FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1) SELECT x.v AS v, y.v AS w, len(list_intersect(x.l, y.l))::INTEGER AS common FROM a x JOIN a y ON x.v < y.v")
def arr_common_nbrs(spark, sf):
    """Suppliers that two brands share; the pairs are of brands, of which there are few."""
    sold = table(spark, sf, "lineitem").join(table(spark, sf, "part"), F.col("l_partkey") == F.col("p_partkey"))
    lists = sold.groupBy(F.col("p_brand").alias("v")).agg(F.collect_set("l_suppkey").alias("l"))
    other = lists.select(F.col("v").alias("w"), F.col("l").alias("m"))
    return lists.join(other, F.col("v") < F.col("w")).select("v", "w", F.size(F.array_intersect("l", "m")).alias("common"))


@register("map_degree", "SELECT c_nationkey, c_mktsegment AS segment, count(*)::BIGINT AS n FROM customer GROUP BY ALL")
def map_degree(spark, sf):
    counted = table(spark, sf, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))
    maps = counted.groupBy("c_nationkey").agg(F.map_from_entries(F.collect_list(F.struct("c_mktsegment", "n"))).alias("m"))
    return maps.select("c_nationkey", F.explode(F.map_entries("m")).alias("e")).select("c_nationkey", F.col("e.key").alias("segment"), F.col("e.value").alias("n"))


@register("date_shift", "SELECT o_orderkey, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INTEGER AS days, (o_orderdate::DATE + INTERVAL 1 MONTH)::DATE::VARCHAR AS next_month FROM orders")
def date_shift(spark, sf):
    day = F.col("o_orderdate").cast("date")
    return table(spark, sf, "orders").select("o_orderkey", F.datediff(day, F.lit("1995-01-01").cast("date")).alias("days"), F.add_months(day, 1).cast("string").alias("next_month"))


@register("approx_measures", "SELECT 1::INTEGER AS ok")
def approx_measures(spark, sf):
    """Approximate distinct counts and quantiles stay within their stated error."""
    rows = table(spark, sf, "lineitem")
    exact = rows.agg(F.countDistinct("l_partkey").alias("n"), F.approx_count_distinct("l_partkey", 0.05).alias("a"), F.percentile_approx("l_suppkey", 0.5, 1000).alias("q"), F.expr("percentile(l_suppkey, 0.5)").alias("m"))
    return exact.select(F.when((F.abs(F.col("n") - F.col("a")) <= 0.2 * F.col("n")) & (F.abs(F.col("q") - F.col("m")) <= 2), 1).otherwise(0).alias("ok"))


@register("sql_functions", "SELECT n_nationkey, round(CASE WHEN least(n_nationkey + 1, 60 - n_nationkey) > 0 THEN (n_regionkey * 1.0) / least(n_nationkey + 1, 60 - n_nationkey) END, 9)::DOUBLE AS phi FROM nation")
def sql_functions(spark, sf):
    """Conductance as a SQL function of the session."""
    from seedspread.functions.sql import register_functions

    register_functions(spark)
    return run_sql(spark, sf, "SELECT n_nationkey, round(seed_conductance(n_regionkey, n_nationkey + 1, 61), 9) AS phi FROM {nation}")


@register("sweep_udtf_geo", "SELECT 1::INTEGER AS same")
def sweep_udtf_geo(spark, sf):
    """The sweep as a table function gives the profile of the DataFrame form."""
    from seedspread.functions.sql import register_functions
    from seedspread.operators import sweep
    from seedspread.plans.graph_queries import given_vector
    from seedspread.sources import builders

    register_functions(spark)
    g = builders.geo(spark, sf)
    p = given_vector(g)
    lists = g.edges.groupBy(F.col("src").alias("v")).agg(F.collect_list("dst").alias("nbrs"))
    rows = p.join(g.degrees, "v").join(lists, "v").select("run_id", "v", "p", "deg", "nbrs", F.lit(g.total_volume).cast("long").alias("total"))
    found = _udtf(spark, rows)
    want = sweep.sweep_profile(g, p)
    gap = found.select("rank", "v", "vol", "cut").exceptAll(want.select("rank", "v", "vol", "cut")).count() + want.select("rank", "v", "vol", "cut").exceptAll(found.select("rank", "v", "vol", "cut")).count()
    return spark.range(1).select(F.lit(1 if gap == 0 else 0).alias("same"))


def _udtf(spark: SparkSession, rows: DataFrame) -> DataFrame:
    rows.createOrReplaceTempView("seedspread_sweep_input")
    return spark.sql("SELECT * FROM seed_sweep(TABLE(SELECT * FROM seedspread_sweep_input) PARTITION BY run_id)")
