"""Relational operators and scalar functions around the clustering, each with the same query in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphmoves.functions.columns import DEC, plogp, portable
from graphmoves.oracle import GRAPH_SQL, U32
from graphmoves.session import snapshot, table
from graphmoves.sources import graphs as G

QUERIES: dict = {}
SQL: dict = {}


def entry(sql: str | None = None):
    """Register a function as a query, under its name, with its SQL."""
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


T = GRAPH_SQL["trade"]
li = lambda s, d: table(s, d, "lineitem")
cust = lambda s, d: table(s, d, "customer")
orders = lambda s, d: table(s, d, "orders")


# --- scans, projections, filters -------------------------------------------------------------------


@entry("SELECT l_orderkey, l_suppkey FROM lineitem WHERE l_shipdate >= TIMESTAMP '1998-01-01'")
def scan_parquet_pruned(s, d):
    return li(s, d).where(F.col("l_shipdate") >= F.to_timestamp(F.lit("1998-01-01"))).select("l_orderkey", "l_suppkey")


@entry(f"SELECT least(a, b) AS lo, greatest(a, b) AS hi, CAST(w AS INT) AS w FROM ({T})")
def proj_edge_direction(s, d):
    return G.trade(s, d).select(F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi"), F.col("w").cast("int").alias("w"))


@entry("SELECT n_nationkey, n_regionkey FROM nation")
def proj_star_except(s, d):
    t = table(s, d, "nation")
    return t.drop(*[c for c in t.columns if c not in ("n_nationkey", "n_regionkey")])


@entry(f"SELECT a, b, w FROM ({GRAPH_SQL['copurchase']}) WHERE w >= 2")
def filter_min_weight(s, d):
    return G.copurchase(s, d).where("w >= 2")


@entry(f"SELECT a, b, w FROM ({T}) WHERE {U32.format(chr(97) + chr(32) + '|| ' + chr(39) + ':0:0' + chr(39))} % 4 = 1")
def filter_active_nodes(s, d):
    return G.trade(s, d).where(portable(F.col("a"), 0, 0) % 4 == 1)


@entry("SELECT c_custkey FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE n_regionkey IN (1, 3)")
def filter_isin_region(s, d):
    return cust(s, d).join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).where(F.col("n_regionkey").isin(1, 3)).select("c_custkey")


@entry("SELECT o_orderkey FROM orders WHERE o_orderdate BETWEEN TIMESTAMP '1996-01-01' AND TIMESTAMP '1996-12-31'")
def filter_between_dates(s, d):
    return orders(s, d).where(F.col("o_orderdate").between(F.to_timestamp(F.lit("1996-01-01")), F.to_timestamp(F.lit("1996-12-31")))).select("o_orderkey")


@entry("SELECT p_partkey FROM part WHERE p_brand LIKE '%1%' AND regexp_matches(p_brand, '[0-9]2$')")
def filter_like_brand(s, d):
    return table(s, d, "part").where(F.col("p_brand").like("%1%") & F.col("p_brand").rlike("[0-9]2$")).select("p_partkey")


@entry("SELECT doc_id FROM documents WHERE lang IS NOT DISTINCT FROM 'en'")
def filter_null_safe(s, d):
    return table(s, d, "documents").where(F.col("lang").eqNullSafe("en")).select("doc_id")


# --- joins -----------------------------------------------------------------------------------------


@entry("SELECT o_custkey, l_suppkey, l_orderkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def join_trade(s, d):
    return li(s, d).join(orders(s, d), F.col("l_orderkey") == F.col("o_orderkey")).select("o_custkey", "l_suppkey", "l_orderkey")


_LABELLED = f"SELECT a, b, w, CAST(c_nationkey AS BIGINT) AS c FROM ({GRAPH_SQL['planted']}) JOIN customer ON a = c_custkey"


def _labelled(s, d, hint):
    return G.planted(s, d).join(G.planted_truth(s, d).withColumnRenamed("id", "a").hint(hint), "a").select("a", "b", "w", "c")


@entry(_LABELLED)
def join_labels_broadcast(s, d):
    return _labelled(s, d, "broadcast")


@entry(_LABELLED)
def join_labels_merge(s, d):
    return _labelled(s, d, "merge")


@entry(_LABELLED)
def join_labels_shuffle_hash(s, d):
    return _labelled(s, d, "shuffle_hash")


_MOVES = "SELECT c_custkey AS v, c_custkey % 5 AS n FROM customer WHERE c_custkey % 3 = 0"


@entry(f"SELECT c_custkey AS id, CAST(coalesce(n, c_nationkey) AS BIGINT) AS c FROM customer LEFT JOIN ({_MOVES}) ON v = c_custkey")
def join_left_carry_inactive(s, d):
    moves = cust(s, d).where("c_custkey % 3 = 0").selectExpr("c_custkey as id", "c_custkey % 5 as n")
    return G.planted_truth(s, d).join(moves, "id", "left").select("id", F.coalesce("n", "c").cast("long").alias("c"))


@entry(f"SELECT c_custkey AS id, n FROM ({_MOVES}) RIGHT JOIN customer ON v = c_custkey")
def join_right_truth(s, d):
    moves = cust(s, d).where("c_custkey % 3 = 0").selectExpr("c_custkey as id", "c_custkey % 5 as n")
    return moves.join(G.planted_truth(s, d), "id", "right").select("id", "n")


@entry("SELECT coalesce(x.c_custkey, y.s_suppkey) AS id, x.c_nationkey AS c1, y.s_nationkey AS c2 FROM customer x FULL JOIN supplier y ON x.c_custkey = y.s_suppkey")
def join_full_labelings(s, d):
    one, two = cust(s, d).selectExpr("c_custkey as id", "c_nationkey as c1"), table(s, d, "supplier").selectExpr("s_suppkey as id", "s_nationkey as c2")
    return one.join(two, "id", "full").select("id", "c1", "c2")


@entry(GRAPH_SQL["copurchase"])
def join_self_copurchase(s, d):
    x = li(s, d).select("l_orderkey", F.col("l_partkey").alias("a"))
    return x.join(x.withColumnRenamed("a", "b"), "l_orderkey").where("a < b").groupBy("a", "b").agg(F.count("*").alias("w"))


@entry("SELECT x.user_id, x.event_type, x.n, y.m FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) x JOIN (SELECT user_id, event_type, round(max(value), 9) AS m FROM events GROUP BY 1, 2) y USING (user_id, event_type)")
def join_using_multi_key(s, d):
    e = table(s, d, "events").groupBy("user_id", "event_type")
    return e.agg(F.count("*").alias("n")).join(e.agg(F.round(F.max("value"), 9).alias("m")), on=["user_id", "event_type"])


@entry("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def semi_nodes_with_edges(s, d):
    return cust(s, d).join(orders(s, d), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@entry("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def anti_isolated_nodes(s, d):
    return cust(s, d).join(orders(s, d), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


_BINS = [(0, 50), (50, 60), (60, 70), (70, 1 << 40)]


@entry("SELECT lo, count(*) AS n FROM (SELECT c_nationkey, count(*) AS s FROM customer GROUP BY 1) JOIN (VALUES (CAST(0 AS BIGINT), CAST(50 AS BIGINT)), (50, 60), (60, 70), (70, 1099511627776)) b(lo, hi) ON s >= lo AND s < hi GROUP BY lo")
def range_size_bucket(s, d):
    sizes = cust(s, d).groupBy("c_nationkey").agg(F.count("*").alias("s"))
    return sizes.join(F.broadcast(s.createDataFrame(_BINS, "lo long, hi long")), (F.col("s") >= F.col("lo")) & (F.col("s") < F.col("hi"))).groupBy("lo").agg(F.count("*").alias("n"))


@entry("SELECT x.n_nationkey AS a, y.n_nationkey AS b FROM nation x JOIN nation y ON x.n_nationkey < y.n_nationkey")
def theta_lower_pairs(s, d):
    n = table(s, d, "nation")
    return n.select(F.col("n_nationkey").alias("a")).join(F.broadcast(n.select(F.col("n_nationkey").alias("b"))), F.col("a") < F.col("b"))


@entry(f"SELECT a, b, w, t FROM ({T}), (SELECT CAST(sum(w) AS BIGINT) AS t FROM ({T}))")
def cross_total_cut(s, d):
    g = G.trade(s, d)
    return g.crossJoin(F.broadcast(g.agg(F.sum("w").alias("t"))))


@entry("""SELECT c.event_id, p.event_id AS purchase FROM (SELECT * FROM events WHERE event_type = 'click') c ASOF LEFT JOIN
    (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) p ON c.user_id = p.user_id AND c.ts >= p.ts""")
def asof_event_purchase(s, d):
    """A union and a window: last purchase at or before each click of the same user."""
    e = table(s, d, "events").where(F.col("event_type").isin("click", "purchase"))
    own = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    w = Window.partitionBy("user_id").orderBy("ts", F.desc("event_type"), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("purchase", F.last(own, True).over(w)).where("event_type = 'click'").select("event_id", "purchase")


@entry("""SELECT x.event_id AS e1, y.event_id AS e2 FROM events x JOIN events y ON x.event_type = y.event_type AND x.user_id < y.user_id
    AND epoch(y.ts) - epoch(x.ts) BETWEEN -60 AND 60""")
def interval_coactive(s, d):
    """Events of two users within a minute: an equi-join on minute buckets, neighbours included, then the exact test."""
    e = table(s, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    b = F.floor(F.col("t") / 60_000_000)
    x = e.withColumn("b", F.explode(F.array(b - 1, b, b + 1)))
    y = e.select(F.col("event_id").alias("e2"), F.col("user_id").alias("u2"), "event_type", F.col("t").alias("t2"), b.alias("b"))
    return x.join(y, ["event_type", "b"]).where("user_id < u2 and abs(t2 - t) <= 60000000").select(F.col("event_id").alias("e1"), "e2")


# --- aggregates ------------------------------------------------------------------------------------


@entry(f"SELECT a AS id, CAST(sum(w) AS BIGINT) AS deg, count(*) AS n FROM (SELECT a, w FROM ({T}) UNION ALL SELECT b, w FROM ({T})) GROUP BY 1")
def agg_degree(s, d):
    g = G.trade(s, d)
    return g.select("a", "w").union(g.select("b", "w")).groupBy(F.col("a").alias("id")).agg(F.sum("w").alias("deg"), F.count("*").alias("n"))


@entry(f"SELECT a AS v, arg_max(b, w * 1000000 - b) AS best FROM ({T}) GROUP BY a")
def agg_best_bid_sort(s, d):
    return G.trade(s, d).groupBy(F.col("a").alias("v")).agg(F.max(F.struct("w", (-F.col("b")).alias("k"))).alias("m")).select("v", (-F.col("m.k")).alias("best"))


@entry("SELECT c_nationkey, arg_max(c_custkey, c_acctbal) AS richest, arg_min(c_custkey, c_acctbal) AS poorest FROM customer GROUP BY 1")
def agg_argmax(s, d):
    """Of equal balances the smallest key, which the SQL meets first in a table ordered by key."""
    by = lambda sign: F.when(F.col("c_acctbal").isNotNull() & F.col("c_custkey").isNotNull(), F.struct("c_acctbal", sign * F.col("c_custkey")))
    return cust(s, d).groupBy("c_nationkey").agg(F.max_by("c_custkey", by(-1)).alias("richest"), F.min_by("c_custkey", by(1)).alias("poorest"))


@entry("SELECT o_custkey, count(DISTINCT l_suppkey) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def agg_distinct_neighbour_clusters(s, d):
    return join_trade(s, d).groupBy("o_custkey").agg(F.count_distinct("l_suppkey").alias("n"))


@entry()
def agg_approx_distinct(s, d):
    return join_trade(s, d).groupBy("o_custkey").agg(F.approx_count_distinct("l_suppkey").alias("n"))


@entry(f"SELECT round(quantile_cont(w, 0.25), 9) AS q1, round(median(w), 9) AS q2, round(quantile_cont(w, 0.9), 9) AS q3 FROM ({GRAPH_SQL['copurchase']})")
def agg_percentiles(s, d):
    return G.copurchase(s, d).agg(*[F.round(F.percentile("w", p), 9).alias(n) for n, p in (("q1", 0.25), ("q2", 0.5), ("q3", 0.9))])


@entry("SELECT n_regionkey, array_to_string(list(n_nationkey ORDER BY n_nationkey), ',') AS members FROM nation GROUP BY 1")
def agg_collect_members(s, d):
    return table(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.transform(F.sort_array(F.collect_list("n_nationkey")), lambda x: x.cast("string")), ",").alias("members"))


@entry("SELECT c_nationkey, bool_and(c_acctbal > 0) AS all_pos, bool_or(c_acctbal > 9000) AS any_rich FROM customer GROUP BY 1")
def agg_bool(s, d):
    return cust(s, d).groupBy("c_nationkey").agg(F.bool_and(F.col("c_acctbal") > 0).alias("all_pos"), F.bool_or(F.col("c_acctbal") > 9000).alias("any_rich"))


@entry("SELECT c_nationkey, round(avg(c_acctbal), 6) AS m, round(stddev_samp(c_acctbal), 6) AS sd, round(corr(c_acctbal, c_custkey), 6) AS r FROM customer GROUP BY 1")
def agg_stats_runs(s, d):
    return cust(s, d).groupBy("c_nationkey").agg(F.round(F.avg("c_acctbal"), 6).alias("m"), F.round(F.stddev_samp("c_acctbal"), 6).alias("sd"), F.round(F.corr("c_acctbal", F.col("c_custkey").cast("double")), 6).alias("r"))


@entry(f"SELECT count(*) FILTER (WHERE w > 1) AS heavy, count(*) AS n FROM ({T})")
def agg_filter_clause(s, d):
    return G.trade(s, d).agg(F.count_if(F.col("w") > 1).alias("heavy"), F.count("*").alias("n"))


@entry("SELECT c_nationkey, count(*) AS n FROM customer GROUP BY 1 HAVING count(*) > 60")
def agg_having(s, d):
    return cust(s, d).groupBy("c_nationkey").agg(F.count("*").alias("n")).where("n > 60")


@entry("SELECT n_regionkey, c_nationkey, count(*) AS n, CAST(grouping(n_regionkey) * 2 + grouping(c_nationkey) AS BIGINT) AS g FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, c_nationkey)")
def rollup_region_nation(s, d):
    j = cust(s, d).join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.rollup("n_regionkey", "c_nationkey").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))


@entry("SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY CUBE (c_mktsegment, c_nationkey)")
def cube_segment_nation(s, d):
    return cust(s, d).cube("c_mktsegment", "c_nationkey").agg(F.count("*").alias("n"))


@entry("SELECT p_type, p_brand, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_type), (p_brand))")
def grouping_sets_type_brand(s, d):
    return table(s, d, "part").groupingSets([["p_type"], ["p_brand"]], "p_type", "p_brand").agg(F.count("*").alias("n"))


@entry("SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY 1")
def pivot_runs_algo(s, d):
    p = table(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "purchase"]).agg(F.count("event_id"))
    return p.na.fill(0)


@entry("SELECT n_nationkey, 'key' AS what, CAST(n_nationkey AS BIGINT) AS v FROM nation UNION ALL SELECT n_nationkey, 'region', CAST(n_regionkey AS BIGINT) FROM nation")
def unpivot_scores(s, d):
    t = table(s, d, "nation").selectExpr("n_nationkey", "cast(n_nationkey as bigint) as key", "cast(n_regionkey as bigint) as region")
    return t.unpivot("n_nationkey", ["key", "region"], "what", "v")


# --- windows, sorting, sets ------------------------------------------------------------------------

_W = "OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)"


@entry(f"SELECT c_custkey, CAST(row_number() {_W} AS INT) AS rn, CAST(rank() {_W} AS INT) AS rk, CAST(dense_rank() {_W} AS INT) AS dr, CAST(ntile(4) {_W} AS INT) AS nt, round(percent_rank() {_W}, 9) AS pr, round(cume_dist() {_W}, 9) AS cd FROM customer")
def win_rank_hubs(s, d):
    w = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    return cust(s, d).select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"),
                             F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


@entry("SELECT o_orderkey, CAST(date_diff('day', lag(o_orderdate) OVER w, o_orderdate) AS INT) AS gap, lead(o_orderkey) OVER w AS nxt FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def win_lag_lead_orders(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return orders(s, d).select("o_orderkey", F.datediff("o_orderdate", F.lag("o_orderdate").over(w)).alias("gap"), F.lead("o_orderkey").over(w).alias("nxt"))


@entry(f"SELECT a, b, CAST(sum(w) OVER (PARTITION BY a ORDER BY b ROWS UNBOUNDED PRECEDING) AS BIGINT) AS run, round(avg(w) OVER (PARTITION BY a ORDER BY b ROWS 2 PRECEDING), 9) AS avg3 FROM ({T})")
def win_running_sum(s, d):
    w = Window.partitionBy("a").orderBy("b")
    return G.trade(s, d).select("a", "b", F.sum("w").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("run"), F.round(F.avg("w").over(w.rowsBetween(-2, 0)), 9).alias("avg3"))


@entry("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range_interval(s, d):
    w = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-3600, 0)
    return table(s, d, "events").withColumn("sec", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000)).select("event_id", F.count("*").over(w).alias("n"))


@entry("SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l, nth_value(o_orderkey, 2) OVER w AS n FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_first_last_nth(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return orders(s, d).select("o_orderkey", F.first("o_orderkey").over(w).alias("f"), F.last("o_orderkey").over(w).alias("l"), F.nth_value("o_orderkey", 2).over(w).alias("n"))


@entry(f"SELECT a, b, max(CASE WHEN b % 3 = 0 THEN w END) OVER (PARTITION BY a) AS own FROM ({T})")
def win_own_bid_spread(s, d):
    return G.trade(s, d).select("a", "b", F.max(F.when(F.col("b") % 3 == 0, F.col("w"))).over(Window.partitionBy("a")).alias("own"))


@entry(f"SELECT id, deg FROM (SELECT a AS id, CAST(sum(w) AS BIGINT) AS deg FROM ({T}) GROUP BY 1) ORDER BY deg DESC, id LIMIT 20")
def topk_hubs(s, d):
    return G.trade(s, d).groupBy(F.col("a").alias("id")).agg(F.sum("w").alias("deg")).orderBy(F.desc("deg"), "id").limit(20)


@entry("SELECT o_orderkey, o_custkey FROM orders ORDER BY o_orderdate DESC NULLS LAST, o_orderkey LIMIT 30 OFFSET 10")
def limit_offset(s, d):
    return orders(s, d).orderBy(F.desc_nulls_last("o_orderdate"), "o_orderkey").offset(10).limit(30).select("o_orderkey", "o_custkey")


@entry("SELECT c_custkey, c_acctbal FROM customer ORDER BY c_mktsegment NULLS FIRST, c_acctbal DESC NULLS LAST")
def sort_multi_nulls(s, d):
    return cust(s, d).orderBy(F.asc_nulls_first("c_mktsegment"), F.desc_nulls_last("c_acctbal")).select("c_custkey", "c_acctbal")


@entry(f"SELECT a, b, w FROM ({T}) QUALIFY row_number() OVER (PARTITION BY a ORDER BY w DESC, b) <= 3")
def topk_bids_per_node(s, d):
    w = Window.partitionBy("a").orderBy(F.desc("w"), "b")
    return G.trade(s, d).withColumn("r", F.row_number().over(w)).where("r <= 3").drop("r")


@entry()
def sort_within_partitions(s, d):
    return G.trade(s, d).repartition("a").sortWithinPartitions("a", "b")


@entry(f"SELECT a AS src, b AS dst, w FROM ({T}) UNION ALL SELECT b, a, w FROM ({T})")
def union_directions(s, d):
    g = G.trade(s, d)
    return g.selectExpr("a as src", "b as dst", "w").unionByName(g.selectExpr("b as src", "a as dst", "w"))


@entry(f"SELECT a AS id FROM ({T}) UNION SELECT b FROM ({T})")
def union_distinct_nodes(s, d):
    g = G.trade(s, d)
    return g.select(F.col("a").alias("id")).union(g.select("b")).distinct()


@entry("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def intersect_neighbours(s, d):
    return cust(s, d).select(F.col("c_nationkey").alias("k")).intersect(table(s, d, "supplier").select("s_nationkey"))


@entry("SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
def intersect_all(s, d):
    return cust(s, d).select(F.col("c_nationkey").alias("k")).intersectAll(table(s, d, "supplier").select("s_nationkey"))


@entry("SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def except_all(s, d):
    return cust(s, d).select(F.col("c_nationkey").alias("k")).exceptAll(table(s, d, "supplier").select("s_nationkey"))


@entry("SELECT c_custkey AS id, c_nationkey AS c FROM customer EXCEPT SELECT c_custkey, c_custkey % 25 FROM customer")
def except_moved(s, d):
    c = cust(s, d)
    return c.selectExpr("c_custkey as id", "cast(c_nationkey as bigint) as c").subtract(c.selectExpr("c_custkey", "c_custkey % 25"))


# --- subqueries, recursion, triangles --------------------------------------------------------------


def _sql(text: str, names: list[str]):
    """The same text in Spark SQL over the named tables."""
    def run(s: SparkSession, d: str) -> DataFrame:
        for n in names:
            table(s, d, n).createOrReplaceTempView(n)
        return s.sql(text)

    return run


for _name, _names, _text in (
    ("subq_scalar_volume", ["customer"], "SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer)"),
    ("subq_correlated_best", ["orders"], "SELECT o_orderkey FROM orders o WHERE o_orderdate = (SELECT max(i.o_orderdate) FROM orders i WHERE i.o_custkey = o.o_custkey)"),
    ("subq_exists", ["customer", "supplier"], "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM supplier WHERE s_nationkey = c_nationkey)"),
    ("subq_in", ["customer", "nation"], "SELECT c_custkey FROM customer WHERE c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 2)"),
    ("cte_chain", ["customer"], "WITH a AS (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1), b AS (SELECT max(n) AS m FROM a) SELECT k, n FROM a, b WHERE n = m"),
    ("lateral_top_neighbours", ["nation", "customer"], "SELECT n_nationkey, x.c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3) x"),
):
    QUERIES[_name], SQL[_name] = _sql(_text, _names), _text

_DESCENT = """WITH RECURSIVE t(id, depth) AS (SELECT CAST(7 AS BIGINT), 0 UNION ALL SELECT l.a, t.depth + 1 FROM t JOIN links4 l ON l.b = t.id)
    SELECT depth, count(*) AS n FROM t GROUP BY depth"""


@entry(f"WITH RECURSIVE links4 AS ({GRAPH_SQL['geo']}), {_DESCENT[15:]}")
def recursive_geo_descent(s, d):
    G.geo(s, d).createOrReplaceTempView("links4")
    return s.sql(_DESCENT)


@entry(f"""WITH RECURSIVE p AS ({GRAPH_SQL['geo']}), e AS (SELECT a, b FROM p UNION ALL SELECT b, a FROM p),
    r AS (SELECT a AS id, a AS c FROM e UNION SELECT r.id, e.b FROM r JOIN e ON e.a = r.c WHERE e.b % 4 = 3 OR e.b % 4 = 2 AND r.c % 4 <> 3), top AS (SELECT id, max(c) FILTER (c % 4 = 3) AS root FROM r GROUP BY id),
    least_of AS (SELECT root, min(id) AS c FROM top GROUP BY root)
    SELECT id, least_of.c FROM top JOIN least_of USING (root)""")
def components_geo(s, d):
    return components(G.geo(s, d))


def components(pairs: DataFrame) -> DataFrame:
    """id, c: least id of each component, by labels that jump to their label's label."""
    both = snapshot(pairs.select("a", "b").union(pairs.select("b", "a")).where("a <> b").distinct())
    labels = snapshot(both.groupBy(F.col("a").alias("id")).agg(F.least(F.min("b"), F.first("a")).alias("c")))
    while True:
        near = both.join(labels.withColumnRenamed("id", "b"), "b").groupBy(F.col("a").alias("id")).agg(F.min("c").alias("m"))
        low = labels.join(near, "id").select("id", F.least("c", "m").alias("c"), F.col("c").alias("was"))
        new = snapshot(low.join(labels.selectExpr("id as c", "c as cc"), "c", "left").select("id", F.least("c", F.coalesce("cc", "c")).alias("c"), "was"))
        if not new.where("c < was").limit(1).count():
            return new.select("id", "c")
        labels = new.select("id", "c")


@entry(f"""WITH p AS (SELECT a, b FROM ({GRAPH_SQL['copurchase']}) WHERE w >= 2), t AS (SELECT x.a AS i, x.b AS j, y.b AS k FROM p x JOIN p y ON x.b = y.a JOIN p z ON z.a = x.a AND z.b = y.b)
    SELECT id, count(*) AS n FROM (SELECT i AS id FROM t UNION ALL SELECT j FROM t UNION ALL SELECT k FROM t) GROUP BY 1""")
def triangles_per_node(s, d):
    """Edges point from lower to higher degree, so no hub expands all its pairs."""
    p = snapshot(G.copurchase(s, d).where("w >= 2").select("a", "b"))
    deg = p.select(F.col("a").alias("id")).union(p.select("b")).groupBy("id").agg(F.count("*").alias("k"))
    q = p.join(deg.selectExpr("id as a", "k as ka"), "a").join(deg.selectExpr("id as b", "k as kb"), "b")
    up = F.col("ka") * (1 << 40) + F.col("a") < F.col("kb") * (1 << 40) + F.col("b")
    o = snapshot(q.select(F.when(up, F.col("a")).otherwise(F.col("b")).alias("x"), F.when(up, F.col("b")).otherwise(F.col("a")).alias("y")))
    two = o.join(o.selectExpr("x as x", "y as z"), "x").where("y < z")
    t = two.join(o.select(F.least("x", "y").alias("y"), F.greatest("x", "y").alias("z")), ["y", "z"])
    return t.select(F.explode(F.array("x", "y", "z")).alias("id")).groupBy("id").agg(F.count("*").alias("n"))


# --- scalar functions ------------------------------------------------------------------------------


@entry("SELECT p_partkey, lower(p_type) AS lo, upper(p_brand) AS up, CAST(length(p_type) AS INT) AS n, substr(p_type, 2, 3) AS mid, replace(p_brand, '#', '-') AS rep, lpad(p_brand, 12, '*') AS pad, reverse(p_brand) AS rev, CAST(instr(p_type, 'E') AS INT) AS pos, regexp_extract(p_brand, '([0-9]+)', 1) AS num, CAST(levenshtein(p_brand, 'Brand#11') AS INT) AS lev FROM part")
def fn_string(s, d):
    t, b = F.col("p_type"), F.col("p_brand")
    return table(s, d, "part").select("p_partkey", F.lower(t).alias("lo"), F.upper(b).alias("up"), F.length(t).alias("n"), F.substring(t, 2, 3).alias("mid"), F.replace(b, F.lit("#"), F.lit("-")).alias("rep"),
                                      F.lpad(b, 12, "*").alias("pad"), F.reverse(b).alias("rev"), F.instr(t, "E").alias("pos"), F.regexp_extract(b, "([0-9]+)", 1).alias("num"), F.levenshtein(b, F.lit("Brand#11")).alias("lev"))


@entry("SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS t FROM pages")
def fn_href_extract(s, d):
    return table(s, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("t"))


@entry("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host FROM pages")
def fn_url_parts(s, d):
    return table(s, d, "pages").select("page_id", F.coalesce(F.parse_url("url", F.lit("HOST")), F.lit("")).alias("host"))


@entry(f"SELECT c_custkey, {U32.format(chr(99) + '_custkey || ' + chr(39) + ':3:1' + chr(39))} % 4 AS r, md5(c_mktsegment) AS h FROM customer")
def fn_portable_activation(s, d):
    return cust(s, d).select("c_custkey", (portable(F.col("c_custkey"), 3, 1) % 4).alias("r"), F.md5("c_mktsegment").alias("h"))


@entry("SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, CAST(dayofweek(o_orderdate) AS INT) + 1 AS dow, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS dd, CAST(epoch(o_orderdate) AS BIGINT) AS u FROM orders")
def fn_dates(s, d):
    o = F.col("o_orderdate")
    return orders(s, d).select("o_orderkey", F.year(o).alias("y"), F.month(o).alias("m"), F.dayofweek(o).alias("dow"), F.datediff(o, F.lit("1995-01-01").cast("date")).cast("long").alias("dd"), F.floor(F.unix_micros(o.cast("timestamp")) / 1_000_000).alias("u"))


@entry("SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS h, count(*) AS n FROM events GROUP BY 1")
def fn_hour_bucket(s, d):
    return table(s, d, "events").groupBy(F.unix_timestamp(F.date_trunc("hour", F.col("ts").cast("timestamp"))).alias("h")).agg(F.count("*").alias("n"))


@entry("SELECT l_orderkey, l_partkey, l_suppkey % 7 AS m, round(sqrt(l_partkey), 6) AS r, round(ln(l_partkey + 1), 6) AS l, CAST(floor(l_partkey / 3.0) AS BIGINT) AS f, greatest(l_partkey, l_suppkey) AS g FROM lineitem")
def fn_math(s, d):
    p = F.col("l_partkey")
    return li(s, d).select("l_orderkey", "l_partkey", F.pmod("l_suppkey", F.lit(7)).cast("long").alias("m"), F.round(F.sqrt(p), 6).alias("r"), F.round(F.ln(p + 1), 6).alias("l"), F.floor(p / 3.0).alias("f"), F.greatest("l_partkey", "l_suppkey").alias("g"))


@entry("SELECT c_custkey, round(CASE WHEN c_custkey > 0 THEN (c_custkey / 1000.0::DOUBLE) * ln(c_custkey / 1000.0::DOUBLE) ELSE 0 END, 9) AS p FROM customer")
def fn_plogp(s, d):
    return cust(s, d).select("c_custkey", F.round(plogp(F.col("c_custkey") / 1000.0), 9).alias("p"))


@entry("SELECT o_orderkey, CAST(CAST(o_orderkey AS HUGEINT) * 9000000000000000000 - o_custkey AS VARCHAR) AS g FROM orders")
def fn_exact_gain(s, d):
    wide = lambda c: c.cast("decimal(19,0)")
    g = (wide(F.col("o_orderkey")) * wide(F.lit(9_000_000_000_000_000_000))).cast(DEC) - F.col("o_custkey").cast(DEC)
    return orders(s, d).select("o_orderkey", g.cast(DEC).cast("string").alias("g"))


@entry(f"SELECT a, len(l) AS n, array_to_string(list_sort(list_transform(list_filter(l, lambda x: x % 2 = 1), lambda x: x + 1))[1:3], ',') AS t, list_contains(l, 1) AS has FROM (SELECT a, list(b) AS l FROM ({T}) GROUP BY a)")
def fn_array_adjacency(s, d):
    g = G.trade(s, d).groupBy("a").agg(F.collect_list("b").alias("l"))
    t = F.slice(F.sort_array(F.transform(F.filter("l", lambda x: x % 2 == 1), lambda x: x + 1)), 1, 3)
    return g.select("a", F.size("l").cast("long").alias("n"), F.array_join(F.transform(t, lambda x: x.cast("string")), ",").alias("t"), F.array_contains("l", 1).alias("has"))


@entry(r"""SELECT doc_id, len(list_distinct(CASE WHEN len(ws) >= 5 THEN [array_to_string(ws[j : j + 4], ' ') FOR j IN range(1, len(ws) - 3)] ELSE [] END)) AS n
    FROM (SELECT doc_id, list_filter(regexp_split_to_array(text, '\s+'), lambda x: x <> '') AS ws FROM documents)""")
def fn_shingles(s, d):
    ws = F.filter(F.split("text", r"\s+"), lambda w: w != "")
    t = table(s, d, "documents").select("doc_id", ws.alias("ws"))
    sh = F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("ws") - 4), lambda i: F.array_join(F.slice("ws", i, 5), " ")))
    return t.select("doc_id", F.when(F.size("ws") >= 5, F.size(sh)).otherwise(0).cast("long").alias("n"))


@entry("SELECT vec_id, round(list_cosine_similarity(CAST(embedding AS DOUBLE[]), CAST((SELECT embedding FROM embeddings WHERE vec_id = 0) AS DOUBLE[])), 6) AS s FROM embeddings")
def fn_cosine(s, d):
    e = table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    j = e.crossJoin(F.broadcast(e.where("vec_id = 0").select(F.col("v").alias("u"))))
    return j.select("vec_id", F.round(dot("v", "u") / F.sqrt(dot("v", "v") * dot("u", "u")), 6).alias("s"))


@entry(f"SELECT a, CAST(cardinality(m) AS BIGINT) AS n, array_to_string(list_sort(map_keys(m))[1:2], ',') AS ks FROM (SELECT a, map_from_entries(list((b, w))) AS m FROM ({T}) WHERE w > 1 GROUP BY a)")
def fn_map_neighbours(s, d):
    m = G.trade(s, d).groupBy("a").agg(F.map_from_entries(F.collect_list(F.struct("b", "w"))).alias("m")).select("a", F.map_filter("m", lambda k, v: v > 1).alias("m")).where(F.size("m") > 0)
    return m.select("a", F.size("m").cast("long").alias("n"), F.array_join(F.transform(F.slice(F.sort_array(F.map_keys("m")), 1, 2), lambda x: x.cast("string")), ",").alias("ks"))


@entry(f"SELECT a, b, w + 1 AS x FROM ({T})")
def fn_bid_struct(s, d):
    t = G.trade(s, d).select(F.struct("a", "b", "w").alias("s")).withColumn("s", F.col("s").withField("x", F.col("s.w") + 1))
    return t.select("s.a", "s.b", "s.x")


@entry("SELECT event_id, CAST(props ->> '$.k' AS BIGINT) AS k FROM events")
def fn_json_props(s, d):
    return table(s, d, "events").select("event_id", F.from_json("props", "k long").getField("k").alias("k"))


@entry("SELECT event_id, CASE WHEN value > 50 THEN 'hi' ELSE 'lo' END AS c, nullif(event_type, 'click') AS n, coalesce(nullif(event_type, 'view'), 'none') AS o FROM events")
def fn_conditional(s, d):
    e = F.col("event_type")
    return table(s, d, "events").select("event_id", F.when(F.col("value") > 50, "hi").otherwise("lo").alias("c"), F.nullif(e, F.lit("click")).alias("n"), F.coalesce(F.nullif(e, F.lit("view")), F.lit("none")).alias("o"))
