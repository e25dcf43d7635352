"""The relational surface around the methods: one query per operator, with its DuckDB twin."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ebbset.functions.hashing import key_of
from ebbset.operators import updates
from ebbset.plans.workloads import VIEW_SQL, Query
from ebbset.sources import views
from ebbset.sources.views import table

QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def register(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = sql
        return f

    return register


@query("scan_pruned", "SELECT l_returnflag, count(*) AS n, sum(l_linenumber)::BIGINT AS lines FROM lineitem GROUP BY 1")
def scan_pruned(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), F.sum("l_linenumber").alias("lines"))


@query("filter_conjunction", "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderdate >= TIMESTAMP '1995-01-01' AND o_orderstatus IN ('O', 'F') AND o_orderpriority LIKE '1%' AND o_totalprice BETWEEN 1000 AND 200000")
def filter_conjunction(s, d):
    o = table(s, d, "orders")
    keep = (F.col("o_orderdate") >= F.to_timestamp_ntz(F.lit("1995-01-01 00:00:00"))) & F.col("o_orderstatus").isin("O", "F") & F.col("o_orderpriority").like("1%") & F.col("o_totalprice").between(1000, 200000)
    return o.where(keep).select("o_orderkey", "o_custkey")


@query("filter_hash_sample", "SELECT p_partkey FROM part WHERE ('0x' || substr(md5(p_partkey::VARCHAR), 1, 7))::BIGINT % 16 = 0")
def filter_hash_sample(s, d):
    return table(s, d, "part").where(key_of(F.col("p_partkey").cast("string"), 7) % 16 == 0).select("p_partkey")


@query("join_hash", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def join_hash(s, d):
    return table(s, d, "orders").join(table(s, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("join_sort_merge", "SELECT o_orderstatus, l_returnflag, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2")
def join_sort_merge(s, d):
    return table(s, d, "lineitem").join(table(s, d, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus", "l_returnflag").agg(F.count("*").alias("n"))


@query("join_broadcast", "SELECT r_name, count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey GROUP BY 1")
def join_broadcast(s, d):
    small = table(s, d, "nation").join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(s, d, "customer").join(F.broadcast(small), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.count("*").alias("n"))


@query("join_theta_nested_loop", "SELECT a.s_suppkey AS low, b.s_suppkey AS high FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal < b.s_acctbal")
def join_theta(s, d):
    v = table(s, d, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal")
    a, b = v.alias("a"), v.alias("b")
    return a.join(b, F.expr("a.s_nationkey = b.s_nationkey and a.s_acctbal < b.s_acctbal")).select(F.col("a.s_suppkey").alias("low"), F.col("b.s_suppkey").alias("high"))


@query("join_interval_idle", """WITH e AS (SELECT user_id, (props->>'k')::BIGINT AS k, ts, event_id FROM events) SELECT a.event_id AS event_id, count(*) AS near FROM e a JOIN e b
    ON a.user_id = b.user_id AND a.k = b.k AND b.event_id <> a.event_id AND b.ts > a.ts - INTERVAL 2 DAY AND b.ts <= a.ts GROUP BY 1""")
def join_interval(s, d):
    e = views.event_topics(s, d)
    a, b = e.alias("a"), e.alias("b")
    on = F.expr("a.set_id = b.set_id and a.item_id = b.item_id and a.event_id <> b.event_id and b.ts > a.ts - interval 2 days and b.ts <= a.ts")
    return a.join(b, on).groupBy(F.col("a.event_id").alias("event_id")).agg(F.count("*").alias("near"))


@query("join_asof_latest", """WITH e AS (SELECT user_id, ts, event_id FROM events), q AS (SELECT DISTINCT user_id, TIMESTAMP '2024-01-15' AS at FROM events)
    SELECT q.user_id AS user_id, max(e.ts) AS last_ts FROM q LEFT JOIN e ON e.user_id = q.user_id AND e.ts <= q.at GROUP BY 1""")
def join_asof(s, d):
    e = table(s, d, "events").select("user_id", "ts")
    at = F.to_timestamp_ntz(F.lit("2024-01-15 00:00:00"))
    return e.groupBy("user_id").agg(F.max(F.when(F.col("ts") <= at, F.col("ts"))).alias("last_ts"))


@query("join_semi_anti", "SELECT c_custkey, c_custkey IN (SELECT o_custkey FROM orders) AS buys FROM customer")
def join_semi_anti(s, d):
    c, o = table(s, d, "customer").select("c_custkey"), table(s, d, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return c.join(o, "c_custkey", "left_semi").withColumn("buys", F.lit(True)).union(c.join(o, "c_custkey", "left_anti").withColumn("buys", F.lit(False)))


@query("join_full_outer_merge", """WITH a AS (SELECT l_suppkey AS k, count(*) AS n FROM lineitem WHERE l_returnflag = 'R' GROUP BY 1), b AS (SELECT s_suppkey AS k, 1::BIGINT AS n FROM supplier WHERE s_acctbal > 0)
    SELECT coalesce(a.k, b.k) AS k, coalesce(a.n, 0) + coalesce(b.n, 0) AS n FROM a FULL JOIN b ON a.k = b.k""")
def join_full(s, d):
    a = table(s, d, "lineitem").where("l_returnflag = 'R'").groupBy(F.col("l_suppkey").alias("k")).agg(F.count("*").alias("n"))
    b = table(s, d, "supplier").where("s_acctbal > 0").select(F.col("s_suppkey").alias("k"), F.lit(1).cast("long").alias("m"))
    return a.join(b, "k", "full_outer").select("k", (F.coalesce("n", F.lit(0)) + F.coalesce("m", F.lit(0))).alias("n"))


@query("agg_sorted_lists", f"SELECT set_id, md5(string_agg(item_id::VARCHAR, ',' ORDER BY item_id)) AS items FROM ({VIEW_SQL['user_topics']}) GROUP BY 1")
def agg_sorted_lists(s, d):
    items = F.transform(F.sort_array(F.collect_list("item_id")), lambda x: x.cast("string"))
    return views.user_topics(s, d).groupBy("set_id").agg(F.md5(F.array_join(items, ",")).alias("items"))


@query("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT props) AS items FROM events GROUP BY 1")
def agg_distinct(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.countDistinct("props").alias("items"))


@query("agg_conditional", "SELECT l_suppkey, count(*) FILTER (l_returnflag = 'R') AS removals, count(*) FILTER (l_returnflag <> 'R') AS kept FROM lineitem GROUP BY 1")
def agg_conditional(s, d):
    return table(s, d, "lineitem").groupBy("l_suppkey").agg(F.count_if(F.col("l_returnflag") == "R").alias("removals"), F.count_if(F.col("l_returnflag") != "R").alias("kept"))


_CUBE = "SELECT c_mktsegment, n_name, grouping(c_mktsegment, n_name)::BIGINT AS g, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY {}"


def _grouped(how: str):
    def of(s, d):
        j = table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
        return getattr(j, how)("c_mktsegment", "n_name").agg(F.grouping_id().alias("g"), F.count("*").alias("n"))

    return of


query("agg_cube", _CUBE.format("CUBE (c_mktsegment, n_name)"))(_grouped("cube"))
query("agg_rollup", _CUBE.format("ROLLUP (c_mktsegment, n_name)"))(_grouped("rollup"))


@query("agg_grouping_sets", _CUBE.format("GROUPING SETS ((c_mktsegment), (n_name), ())"))
def agg_grouping_sets(s, d):
    j = table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    a, b = F.col("c_mktsegment"), F.col("n_name")
    return j.groupingSets([[a], [b], []], a, b).agg(F.grouping_id().alias("g"), F.count("*").alias("n"))


@query("agg_pivot_genres", "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS \"view\", count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY 1")
def agg_pivot(s, d):
    return table(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "view", "purchase"]).count().fillna(0)


@query("agg_quantiles", "SELECT l_returnflag, median(l_quantity) AS mid, quantile_cont(l_quantity, 0.9) AS high FROM lineitem GROUP BY 1")
def agg_quantiles(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag").agg(F.median("l_quantity").alias("mid"), F.percentile("l_quantity", 0.9).alias("high"))


@query("agg_argmin", "SELECT l_suppkey, arg_min(l_partkey, md5(l_partkey::VARCHAR)) AS least FROM lineitem GROUP BY 1")
def agg_argmin(s, d):
    return table(s, d, "lineitem").groupBy("l_suppkey").agg(F.min_by("l_partkey", F.md5(F.col("l_partkey").cast("string"))).alias("least"))


@query("agg_bit", "SELECT set_id, bit_count(bit_or((1::BIGINT << (item_id % 62)::INTEGER)))::INTEGER AS used, bit_xor(item_id) AS parity FROM (" + VIEW_SQL["user_topics"] + ") GROUP BY 1")
def agg_bit(s, d):
    bit = F.expr("shiftleft(1L, cast(item_id % 62 as int))")
    return views.user_topics(s, d).groupBy("set_id").agg(F.bit_count(F.bit_or(bit)).alias("used"), F.bit_xor("item_id").alias("parity"))


@query("agg_approx_distinct")
def agg_approx(s, d):
    v = views.supplier_parts(s, d)
    return v.groupBy("set_id").agg(F.count("*").alias("exact"), F.approx_count_distinct("item_id", 0.02).alias("hll"), F.theta_sketch_estimate(F.theta_sketch_agg("item_id")).alias("theta"))


@query("win_rank_topk", "SELECT c_nationkey, c_custkey, r, dr, nt FROM (SELECT c_nationkey, c_custkey, rank() OVER w::INTEGER AS r, dense_rank() OVER w::INTEGER AS dr, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)::INTEGER AS nt FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC)) WHERE r <= 5".replace("rank() OVER w::INTEGER", "(rank() OVER w)::INTEGER").replace("dense_(rank() OVER w)::INTEGER", "(dense_rank() OVER w)::INTEGER").replace("ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)::INTEGER", "(ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey))::INTEGER"))
def win_rank(s, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"))
    own = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    c = table(s, d, "customer").select("c_nationkey", "c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(own).alias("nt"))
    return c.where("r <= 5")


@query("win_lag_gap", "SELECT event_id, floor(epoch(ts - lag(ts) OVER w))::BIGINT AS gap, floor(epoch(lead(ts) OVER w - ts))::BIGINT AS until_next FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    seconds = lambda a, b: F.timestamp_diff("SECOND", a, b)
    return table(s, d, "events").select("event_id", seconds(F.lag("ts").over(w), F.col("ts")).alias("gap"), seconds(F.col("ts"), F.lead("ts").over(w)).alias("until_next"))


@query("win_running_net", "SELECT event_id, (sum(CASE WHEN event_type = 'error' THEN -1 ELSE 1 END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING))::BIGINT AS net FROM events")
def win_running(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return table(s, d, "events").select("event_id", F.sum(F.when(F.col("event_type") == "error", -1).otherwise(1)).over(w).alias("net"))


@query("win_range_7d", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 604800 PRECEDING AND CURRENT ROW) AS recent FROM events")
def win_range(s, d):
    w = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-604800, 0)
    # whole seconds by rounding (halves to even), as the SQL's cast has it
    e = table(s, d, "events").withColumn("sec", F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).cast("long"))
    return e.select("event_id", F.count("*").over(w).alias("recent"))


@query("win_first_last", "SELECT DISTINCT user_id, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER w AS last_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_first_last(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(s, d, "events").select("user_id", F.first("event_id").over(w).alias("first_id"), F.last("event_id").over(w).alias("last_id")).distinct()


@query("sort_limit_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def sort_limit(s, d):
    return table(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


_A, _B = (f"SELECT item_id FROM ({VIEW_SQL['supplier_parts']}) WHERE set_id = {k}" for k in (1, 2))


@query("set_union_intersect_except", f"SELECT 'union' AS op, count(*) AS n FROM ({_A} UNION {_B}) UNION ALL SELECT 'intersect', count(*) FROM ({_A} INTERSECT {_B}) UNION ALL SELECT 'except', count(*) FROM ({_A} EXCEPT {_B})")
def set_ops(s, d):
    v = views.supplier_parts(s, d)
    a, b = (v.where(F.col("set_id") == k).select("item_id") for k in (1, 2))
    of = lambda name, x: x.agg(F.lit(name).alias("op"), F.count("*").alias("n"))
    return of("union", a.union(b).distinct()).union(of("intersect", a.intersect(b))).union(of("except", a.subtract(b)))


@query("fn_dates", "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, count(*) AS n, max(date_diff('day', o_orderdate::DATE, (o_orderdate + INTERVAL 45 DAY)::DATE))::INTEGER AS span FROM orders GROUP BY 1")
def fn_dates(s, d):
    day = F.col("o_orderdate").cast("date")
    later = F.expr("cast(o_orderdate + interval 45 days as date)")
    return table(s, d, "orders").groupBy(F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month")).agg(F.count("*").alias("n"), F.max(F.datediff(later, day)).alias("span"))


@query("fn_arrays", f"""WITH v AS (SELECT set_id, list_sort(list(item_id)) AS a FROM ({VIEW_SQL['user_topics']}) GROUP BY 1)
    SELECT x.set_id AS set_id, len(list_intersect(x.a, y.a))::INTEGER AS inter, len(list_distinct(list_concat(x.a, y.a)))::INTEGER AS uni FROM v x JOIN v y ON y.set_id = x.set_id + 1""")
def fn_arrays(s, d):
    v = views.user_topics(s, d).groupBy("set_id").agg(F.sort_array(F.collect_list("item_id")).alias("a"))
    y = v.select((F.col("set_id") - 1).alias("set_id"), F.col("a").alias("b"))
    return v.join(y, "set_id").select("set_id", F.size(F.array_intersect("a", "b")).alias("inter"), F.size(F.array_union("a", "b")).alias("uni"))


@query("fn_json", "SELECT (props->>'k')::INTEGER % 10 AS digit, count(*) AS n FROM events GROUP BY 1")
def fn_json(s, d):
    return table(s, d, "events").groupBy((F.from_json("props", "k int")["k"] % 10).alias("digit")).agg(F.count("*").alias("n"))


@query("fn_maps", "SELECT user_id, event_type AS kind, count(*) AS n FROM events GROUP BY 1, 2")
def fn_maps(s, d):
    counts = table(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return counts.select("user_id", F.explode(F.map_filter("m", lambda k, v: v > 0)).alias("kind", "n"))


@query("sql_text_flow", "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS t FROM orders GROUP BY 1) SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM big WHERE o_custkey = c_custkey AND t > (SELECT avg(o_totalprice) FROM orders))")
def sql_text(s: SparkSession, d: str) -> DataFrame:
    for name in ("orders", "customer"):
        table(s, d, name).createOrReplaceTempView(f"flow_{name}")
    return s.sql("WITH big AS (SELECT o_custkey, sum(o_totalprice) AS t FROM flow_orders GROUP BY 1) SELECT c_custkey FROM flow_customer WHERE EXISTS (SELECT 1 FROM big WHERE o_custkey = c_custkey AND t > (SELECT avg(o_totalprice) FROM flow_orders))")


@query("join_semi_dense_users", f"SELECT set_id, item_id FROM ({VIEW_SQL['user_topics']}) v WHERE set_id IN (SELECT set_id FROM ({VIEW_SQL['user_topics']}) GROUP BY 1 HAVING count(*) >= 50)")
def semi_dense(s, d):
    v = views.user_topics(s, d)
    return v.join(updates.cardinalities(v).where("card >= 50"), "set_id", "left_semi")
