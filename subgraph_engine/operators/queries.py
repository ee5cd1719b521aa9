"""A query and its SQL for each operator."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subgraph_engine import graphs, oracle_sql
from subgraph_engine.functions import sql_surface
from subgraph_engine.operators import library as lib
from subgraph_engine.storage import shared_path
from subgraph_engine.tables import NAMES, load

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}
BASKET = oracle_sql.EDGES["basket"]


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return keep


@query("op_scan_counts", " UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS n FROM {n}" for n in NAMES))
def op_scan_counts(spark, d):
    rows = None
    for n in NAMES:
        row = load(spark, d, n).agg(F.lit(n).alias("name"), F.count(F.lit(1)).alias("n"))
        rows = row if rows is None else rows.unionByName(row)
    return rows


@query("op_project_ids", "SELECT l_orderkey * 2 AS src, l_partkey * 2 + 1 AS dst, CAST(l_quantity AS INTEGER) AS q FROM lineitem")
def op_project_ids(spark, d):
    return load(spark, d, "lineitem").select(graphs.even("l_orderkey").alias("src"), graphs.odd("l_partkey").alias("dst"), F.col("l_quantity").cast("int").alias("q"))


@query(
    "op_filter_edges",
    """SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R')
AND NOT (l_discount < 0.02) AND l_linestatus LIKE 'O%' AND l_shipdate IS NOT NULL""",
)
def op_filter_edges(spark, d):
    c = F.col
    keep = c("l_quantity").between(10, 20) & c("l_returnflag").isin("A", "R") & ~(c("l_discount") < 0.02)
    return load(spark, d, "lineitem").filter(keep & c("l_linestatus").like("O%") & c("l_shipdate").isNotNull()).select("l_orderkey", "l_partkey")


@query(
    "op_induced_subgraph",
    f"""SELECT src, dst FROM ({BASKET}) WHERE src IN (SELECT o_orderkey * 2 FROM orders WHERE o_orderstatus = 'F')
AND dst IN (SELECT p_partkey * 2 + 1 FROM part WHERE p_size > 25)""",
)
def op_induced_subgraph(spark, d):
    """Filled orders and the large parts on them."""
    orders = load(spark, d, "orders").filter("o_orderstatus = 'F'").select(graphs.even("o_orderkey").alias("vid"))
    parts = load(spark, d, "part").filter("p_size > 25").select(graphs.odd("p_partkey").alias("vid"))
    return lib.induced_subgraph(graphs.basket(spark, d).edges, orders.unionByName(parts)).select("src", "dst")


@query("op_wave_prune", f"SELECT CAST(src % 4 AS INTEGER) AS pid, count(*) AS n FROM ({BASKET}) WHERE src % 4 IN (0, 2) GROUP BY 1")
def op_wave_prune(spark, d):
    """Partitions 0 and 2 of a table with a folder each: the others are not listed."""
    path = shared_path(spark, "prune")
    graphs.basket(spark, d).edges.withColumn("pid", (F.col("src") % 4).cast("int")).write.partitionBy("pid").parquet(path)
    return spark.read.parquet(path).filter("pid in (0, 2)").groupBy("pid").agg(F.count(F.lit(1)).alias("n"))


_JOINED = "SELECT o_orderkey, c_name FROM orders {} JOIN customer ON o_custkey = c_custkey"


@query("op_join_inner", _JOINED.format(""))
def op_join_inner(spark, d):
    o, c = load(spark, d, "orders"), load(spark, d, "customer")
    return o.join(c.hint("merge"), o["o_custkey"] == c["c_custkey"]).select("o_orderkey", "c_name")


@query("op_join_hash", _JOINED.format(""))
def op_join_hash(spark, d):
    o, c = load(spark, d, "orders"), load(spark, d, "customer")
    return o.join(c.hint("shuffle_hash"), o["o_custkey"] == c["c_custkey"]).select("o_orderkey", "c_name")


@query("op_join_broadcast", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def op_join_broadcast(spark, d):
    """Nations and regions are tables of fixed size."""
    c, n, r = load(spark, d, "customer"), load(spark, d, "nation"), load(spark, d, "region")
    both = c.join(F.broadcast(n), c["c_nationkey"] == n["n_nationkey"]).join(F.broadcast(r), n["n_regionkey"] == r["r_regionkey"])
    return both.select("c_custkey", "n_name", "r_name")


@query("op_join_outer", "SELECT c_custkey, o_orderkey FROM customer FULL JOIN orders ON c_custkey = o_custkey")
def op_join_outer(spark, d):
    c, o = load(spark, d, "customer"), load(spark, d, "orders")
    return c.join(o, c["c_custkey"] == o["o_custkey"], "full").select("c_custkey", "o_orderkey")


@query("op_join_left", "SELECT p_partkey, count(l_orderkey) AS lines FROM part LEFT JOIN lineitem ON p_partkey = l_partkey GROUP BY p_partkey")
def op_join_left(spark, d):
    p, li = load(spark, d, "part"), load(spark, d, "lineitem")
    return p.join(li, p["p_partkey"] == li["l_partkey"], "left").groupBy("p_partkey").agg(F.count("l_orderkey").alias("lines"))


@query("op_join_right", "SELECT s_suppkey, c_custkey FROM customer RIGHT JOIN supplier ON c_custkey = s_suppkey")
def op_join_right(spark, d):
    c, s = load(spark, d, "customer"), load(spark, d, "supplier")
    return c.join(s, c["c_custkey"] == s["s_suppkey"], "right").select("s_suppkey", "c_custkey")


@query("op_join_semi", "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)")
def op_join_semi(spark, d):
    li = load(spark, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"))
    return load(spark, d, "orders").join(li, "o_orderkey", "left_semi").select("o_orderkey")


@query("op_join_anti", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def op_join_anti(spark, d):
    li = load(spark, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"))
    return load(spark, d, "orders").join(li, "o_orderkey", "left_anti").select("o_orderkey")


_LINES = "SELECT DISTINCT l_orderkey, l_partkey FROM lineitem"


@query("op_join_self", f"SELECT a.l_partkey AS a, b.l_partkey AS b, count(*) AS common FROM ({_LINES}) a JOIN ({_LINES}) b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY ALL")
def op_join_self(spark, d):
    """Wedges: parts with orders in common (an order has few lines, which bounds its pairs)."""
    e = load(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    both = e.withColumnRenamed("l_partkey", "a").join(e.withColumnRenamed("l_partkey", "b"), "l_orderkey").filter("a < b")
    return both.groupBy("a", "b").agg(F.count(F.lit(1)).alias("common"))


_SPANS = "SELECT user_id, min(epoch_us(ts)) AS s, max(epoch_us(ts)) AS e, date_trunc('month', ts) AS m FROM events WHERE event_type = 'purchase' GROUP BY user_id, m"


@query("op_join_range", f"SELECT event_id, m FROM (SELECT event_id, user_id, epoch_us(ts) AS t FROM events) p JOIN ({_SPANS}) s ON p.user_id = s.user_id AND t >= s AND t < e")
def op_join_range(spark, d):
    ev = load(spark, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), F.date_trunc("month", "ts").cast("timestamp_ntz").alias("m"), "event_type")
    spans = ev.filter("event_type = 'purchase'").groupBy("user_id", "m").agg(F.min("t").alias("s"), F.max("t").alias("e"))
    return lib.range_join(ev.drop("m", "event_type"), spans, "t", "s", "e", 7 * 86400e6, ["user_id"]).select("event_id", "m")


@query(
    "op_join_asof",
    """SELECT p.event_id, (SELECT max_by(b.event_id, (b.ts, b.event_id)) FROM events b WHERE b.event_type = 'purchase' AND b.user_id = p.user_id AND b.ts <= p.ts) AS bought
FROM events p WHERE p.event_type = 'click'""",
)
def op_join_asof(spark, d):
    ev = load(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    clicks = ev.filter("event_type = 'click'").select("event_id", "user_id", "ts")
    buys = ev.filter("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("bought"))
    return lib.as_of(clicks, buys, ["user_id"], "ts", "bought").select("event_id", "bought")


@query("op_agg_combiner", f"SELECT dst, min(src) AS lo, max(src) AS hi, count(*) AS n, CAST(sum(src) AS BIGINT) AS total FROM ({BASKET}) GROUP BY dst")
def op_agg_combiner(spark, d):
    e = graphs.basket(spark, d).edges
    return e.groupBy("dst").agg(F.min("src").alias("lo"), F.max("src").alias("hi"), F.count(F.lit(1)).alias("n"), F.sum("src").alias("total"))


@query("op_agg_salted", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def op_agg_salted(spark, d):
    return lib.salted_counts(load(spark, d, "events").select("event_type", "event_id"), "event_type")


@query("op_agg_collect", "SELECT n_regionkey, list(n_nationkey ORDER BY n_nationkey) AS nations FROM nation GROUP BY 1")
def op_agg_collect(spark, d):
    return load(spark, d, "nation").groupBy("n_regionkey").agg(F.sort_array(F.collect_list("n_nationkey")).alias("nations"))


@query("op_agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def op_agg_distinct(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("op_agg_approx")
def op_agg_approx(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@query("op_agg_filter", "SELECT o_orderstatus, count(*) FILTER (o_totalprice > 200000) AS large, CAST(sum(CASE WHEN o_orderkey % 2 = 0 THEN 1 ELSE 0 END) AS BIGINT) AS even FROM orders GROUP BY 1")
def op_agg_filter(spark, d):
    even = F.sum(F.when(F.col("o_orderkey") % 2 == 0, 1).otherwise(0)).alias("even")
    return load(spark, d, "orders").groupBy("o_orderstatus").agg(F.count_if(F.col("o_totalprice") > 200000).alias("large"), even)


for _kind in ("rollup", "cube"):
    query(f"op_agg_{_kind}", f"SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY {_kind} (l_returnflag, l_linestatus)")(
        lambda spark, d, kind=_kind: getattr(load(spark, d, "lineitem"), kind)("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))
    )


@query("op_agg_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def op_agg_grouping_sets(spark, d):
    load(spark, d, "orders").createOrReplaceTempView("graph_orders")
    return spark.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM graph_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


@query("op_agg_bits", "SELECT n_regionkey, bit_or(CAST(1 AS BIGINT) << n_nationkey) AS members, bit_count(bit_or(CAST(1 AS BIGINT) << n_nationkey)) AS n, bit_and(n_nationkey) AS common FROM nation GROUP BY 1")
def op_agg_bits(spark, d):
    members = F.bit_or(F.expr("shiftleft(1L, n_nationkey)"))
    return load(spark, d, "nation").groupBy("n_regionkey").agg(members.alias("members"), F.bit_count(members).cast("tinyint").alias("n"), F.bit_and("n_nationkey").alias("common"))


@query("op_agg_mode", "SELECT user_id, event_type FROM (SELECT user_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY count(*) DESC, event_type) AS r FROM events GROUP BY 1, 2) WHERE r = 1")
def op_agg_mode(spark, d):
    ev = load(spark, d, "events")
    kinds = ev.select("event_type").distinct().withColumn("k", F.dense_rank().over(Window.orderBy("event_type")))  # a handful
    named = ev.join(F.broadcast(kinds), "event_type").select("user_id", "k")
    return lib.most_frequent(named, ["user_id"], "k").join(F.broadcast(kinds), "k").select("user_id", "event_type")


@query("op_agg_stats", "SELECT o_orderpriority, round(avg(o_totalprice), 4) AS mean, round(stddev_samp(o_totalprice), 4) AS sd, max_by(o_orderkey, o_totalprice) AS dearest, min_by(o_orderkey, o_totalprice) AS cheapest, round(quantile_cont(o_totalprice, 0.5), 4) AS median FROM orders GROUP BY 1")
def op_agg_stats(spark, d):
    p = "o_totalprice"
    return load(spark, d, "orders").groupBy("o_orderpriority").agg(
        F.round(F.avg(p), 4).alias("mean"), F.round(F.stddev_samp(p), 4).alias("sd"), F.max_by("o_orderkey", p).alias("dearest"),
        F.min_by("o_orderkey", p).alias("cheapest"), F.round(F.percentile(p, 0.5), 4).alias("median"),
    )


@query("op_win_rank", "SELECT c_custkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS q FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment, c_custkey)")
def op_win_rank(spark, d):
    w = Window.partitionBy("c_nationkey").orderBy("c_mktsegment", "c_custkey")
    return load(spark, d, "customer").select("c_custkey", *(f().over(w).cast("long").alias(n) for f, n in ((F.row_number, "rn"), (F.rank, "rk"), (F.dense_rank, "dr"))), F.ntile(4).over(w).cast("long").alias("q"))


@query("op_win_lag", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after2, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_win_lag(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("after2"), F.first("event_id").over(w).alias("first"))


@query("op_win_frames", "SELECT o_orderkey, CAST(sum(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS last3, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 500 PRECEDING AND 500 FOLLOWING) AS near FROM orders")
def op_win_frames(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return load(spark, d, "orders").select("o_orderkey", F.sum("o_orderkey").over(w.rowsBetween(-2, 0)).alias("last3"), F.count(F.lit(1)).over(w.rangeBetween(-500, 500)).alias("near"))


@query("op_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def op_topk(spark, d):
    return load(spark, d, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice")


@query("op_topk_group", "SELECT o_custkey, o_orderkey, rank FROM (SELECT o_custkey, o_orderkey, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS INTEGER) AS rank FROM orders) WHERE rank <= 3")
def op_topk_group(spark, d):
    return lib.top_per_group(load(spark, d, "orders"), ["o_custkey"], [F.col("o_totalprice").desc(), F.col("o_orderkey")], 3).select("o_custkey", "o_orderkey", "rank")


_A, _B = "SELECT l_partkey AS k FROM lineitem WHERE l_returnflag = 'R'", "SELECT l_partkey AS k FROM lineitem WHERE l_returnflag = 'A'"
for _n, _op, _spark in (
    ("union", "UNION", lambda a, b: a.union(b).distinct()), ("union_all", "UNION ALL", lambda a, b: a.unionByName(b)), ("intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("except", "EXCEPT", lambda a, b: a.subtract(b)), ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    query(f"op_set_{_n}", f"{_A} {_op} {_B}")(
        lambda spark, d, f=_spark: f(*(load(spark, d, "lineitem").filter(c).select(F.col("l_partkey").alias("k")) for c in ("l_returnflag = 'R'", "l_returnflag = 'A'")))
    )


@query("op_pivot", "SELECT o_orderpriority, " + ", ".join(f"count(*) FILTER (o_orderstatus = '{s}') AS {s.lower()}" for s in "FOP") + " FROM orders GROUP BY 1")
def op_pivot(spark, d):
    wide = load(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return wide.select("o_orderpriority", *(F.coalesce(F.col(s), F.lit(0)).cast("long").alias(s.lower()) for s in "FOP"))


@query("op_unpivot", "SELECT s_suppkey, 'nation' AS field, CAST(s_nationkey AS BIGINT) AS x FROM supplier UNION ALL SELECT s_suppkey, 'key', s_suppkey FROM supplier")
def op_unpivot(spark, d):
    s = load(spark, d, "supplier").select("s_suppkey", F.col("s_nationkey").cast("long").alias("nation"), F.col("s_suppkey").alias("key"))
    return s.unpivot("s_suppkey", ["nation", "key"], "field", "x")


@query("op_recursive_bfs", oracle_sql.bfs("geo", "0", "SELECT id AS vid, CAST(d AS INTEGER) AS depth FROM w WHERE d <= 3"))
def op_recursive_bfs(spark, d):
    """The same search as recursive SQL in Spark, three levels of the tree below a region."""
    graphs.geo(spark, d).arcs().createOrReplaceTempView("graph_geo_arcs")
    return spark.sql(
        """WITH RECURSIVE reach(vid, depth, came) AS (
             SELECT 0L, 0, -1L
             UNION ALL SELECT a.dst, r.depth + 1, r.vid FROM reach r JOIN graph_geo_arcs a ON a.src = r.vid WHERE a.dst <> r.came AND r.depth < 3)
           SELECT vid, min(depth) AS depth FROM reach GROUP BY vid"""
    )


@query("op_subquery", f"WITH e AS ({BASKET}), deg AS (SELECT dst AS vid, count(*) AS n FROM e GROUP BY 1) SELECT vid, n FROM deg WHERE n > (SELECT avg(n) FROM deg) AND EXISTS (SELECT 1 FROM part WHERE p_partkey * 2 + 1 = vid AND p_size > 25)")
def op_subquery(spark, d):
    graphs.basket(spark, d).edges.groupBy(F.col("dst").alias("vid")).agg(F.count(F.lit(1)).alias("n")).createOrReplaceTempView("graph_deg")
    load(spark, d, "part").createOrReplaceTempView("graph_part")
    return spark.sql("SELECT vid, n FROM graph_deg g WHERE n > (SELECT avg(n) FROM graph_deg) AND EXISTS (SELECT 1 FROM graph_part p WHERE p.p_partkey * 2 + 1 = g.vid AND p.p_size > 25)")


@query("op_lateral", "SELECT n_nationkey, k, n_nationkey * k AS product FROM nation, LATERAL (SELECT unnest([1, 2, 3]) AS k)")
def op_lateral(spark, d):
    return load(spark, d, "nation").select("n_nationkey", F.explode(F.array(*map(F.lit, (1, 2, 3)))).alias("k")).withColumn("product", F.col("n_nationkey") * F.col("k"))


@query("op_bits", "SELECT o_orderkey, o_orderkey & 12 AS masked, bit_count(o_orderkey) AS ones, (o_orderkey & 7) << 3 AS moved FROM orders")
def op_bits(spark, d):
    k = F.col("o_orderkey")
    return load(spark, d, "orders").select("o_orderkey", k.bitwiseAND(F.lit(12)).alias("masked"), F.bit_count(k).cast("tinyint").alias("ones"), F.shiftleft(k.bitwiseAND(F.lit(7)), 3).alias("moved"))


@query("op_math", "SELECT o_orderkey, o_orderkey // 7 AS q, o_orderkey % 7 AS r, CAST(ceil(o_totalprice / 1000) AS BIGINT) AS k, least(o_orderkey, o_custkey) AS lo, greatest(o_orderkey, o_custkey) AS hi, round(ln(o_totalprice), 6) AS l FROM orders")
def op_math(spark, d):
    c = F.col
    return load(spark, d, "orders").select(
        "o_orderkey", F.expr("o_orderkey div 7").alias("q"), F.pmod("o_orderkey", F.lit(7)).alias("r"), F.ceil(c("o_totalprice") / 1000).alias("k"),
        F.least("o_orderkey", "o_custkey").alias("lo"), F.greatest("o_orderkey", "o_custkey").alias("hi"), F.round(F.log("o_totalprice"), 6).alias("l"),
    )


@query("op_string", "SELECT p_partkey, lower(p_name) AS name, length(p_name) AS n, concat_ws('|', p_brand, p_type) AS k, string_split(p_type, ' ')[1] AS kind, regexp_matches(p_brand, '[0-9]$') AS digit FROM part")
def op_string(spark, d):
    return load(spark, d, "part").select(
        "p_partkey", F.lower("p_name").alias("name"), F.length("p_name").cast("long").alias("n"), F.concat_ws("|", "p_brand", "p_type").alias("k"),
        F.split("p_type", " ")[0].alias("kind"), F.col("p_brand").rlike("[0-9]$").alias("digit"),
    )


@query("op_time", "SELECT event_id, date_trunc('day', ts) AS day, CAST(extract('hour' FROM ts) AS INTEGER) AS hour, ts + INTERVAL 90 MINUTE AS later, epoch_us(ts) AS us FROM events")
def op_time(spark, d):
    ts = F.col("ts")
    return load(spark, d, "events").select(
        "event_id", F.date_trunc("day", ts).cast("timestamp_ntz").alias("day"), F.hour(ts).alias("hour"), (ts + F.expr("interval 90 minutes")).alias("later"), F.unix_micros(ts.cast("timestamp")).alias("us")
    )


_LISTS = "SELECT n_regionkey, list(n_nationkey ORDER BY n_nationkey) AS a FROM nation GROUP BY 1"


@query("op_array", f"SELECT n_regionkey, len(a) AS n, list_transform(a, lambda x: x * 2) AS doubled, list_filter(a, lambda x: x % 2 = 0) AS even, CAST(list_sum(a) AS BIGINT) AS total, a[1:2] AS head, list_contains(a, 3) AS has3 FROM ({_LISTS})")
def op_array(spark, d):
    a = load(spark, d, "nation").groupBy("n_regionkey").agg(F.sort_array(F.collect_list("n_nationkey")).alias("a"))
    return a.select(
        "n_regionkey", F.size("a").cast("long").alias("n"), F.transform("a", lambda x: x * 2).alias("doubled"), F.filter("a", lambda x: x % 2 == 0).alias("even"),
        F.aggregate("a", F.lit(0).cast("long"), lambda s, x: s + x).alias("total"), F.slice("a", 1, 2).alias("head"), F.array_contains("a", 3).alias("has3"),
    )


@query("op_map", f"SELECT n_regionkey, a[1] AS smallest, len(a) AS n FROM ({_LISTS})")
def op_map(spark, d):
    """A payload map from vertex to value, looked up by key."""
    pairs = load(spark, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("n_nationkey", "n_name")))).alias("m"))
    return pairs.select("n_regionkey", F.array_min(F.map_keys("m")).alias("smallest"), F.size("m").cast("long").alias("n"))


@query("op_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def op_json(spark, d):
    return load(spark, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("op_json_text", "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
def op_json_text(spark, d):
    return load(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@query("op_null", "SELECT c_custkey, nullif(c_nationkey, 3) AS n, coalesce(nullif(c_nationkey, 3), -1) AS m, nullif(c_nationkey, 3) IS NOT DISTINCT FROM NULL AS gone FROM customer")
def op_null(spark, d):
    n = F.nullif(F.col("c_nationkey"), F.lit(3))
    return load(spark, d, "customer").select("c_custkey", n.alias("n"), F.coalesce(n, F.lit(-1)).alias("m"), n.eqNullSafe(F.lit(None)).alias("gone"))


@query("op_hash_place")
def op_hash_place(spark, d):
    return load(spark, d, "customer").select("c_custkey", F.pmod(F.xxhash64("c_custkey"), F.lit(8)).alias("pid"), F.crc32(F.col("c_name").cast("binary")).alias("crc"))


@query("op_join_back", f"SELECT component, count(*) AS docs, CAST(sum(toxic) AS BIGINT) AS toxic FROM labels JOIN (SELECT vid, component FROM ({oracle_sql.wcc('doc_dup')})) ON vid = doc_id GROUP BY 1")
def op_join_back(spark, d):
    """Components of copied documents with the labels of their members."""
    from subgraph_engine.algorithms import wcc

    found = wcc(spark, graphs.doc_dup(spark, d), "star")
    labels = load(spark, d, "labels").withColumnRenamed("doc_id", "vid")
    return labels.join(found, "vid").groupBy("component").agg(F.count(F.lit(1)).alias("docs"), F.sum("toxic").alias("toxic"))


@query("op_udf_varint", f"WITH {oracle_sql.graph('geo')} SELECT dst, list(src ORDER BY src) AS nbrs FROM a GROUP BY dst")
def op_udf_varint(spark, d):
    """Neighbour lists packed and unpacked by functions called from SQL."""
    sql_surface.register(spark)
    sql_surface.graph_views(graphs.geo(spark, d))
    return spark.sql("SELECT dst, varint_unpack(varint_pack(collect_list(src))) AS nbrs FROM graph_geo_arcs GROUP BY dst")


@query("op_udtf_payload", f"WITH {oracle_sql.graph('geo')} SELECT dst % 8 AS part, vid, CAST(vid * 3 AS BIGINT) AS value FROM (SELECT DISTINCT dst AS vid, dst FROM a)")
def op_udtf_payload(spark, d):
    """Payloads packed by an aggregate and taken apart by a table function."""
    sql_surface.register(spark)
    sql_surface.graph_views(graphs.geo(spark, d))
    return spark.sql(
        """SELECT part, r.vid, r.value
           FROM (SELECT vid % 8 AS part, payload_pack(vid, vid * 3) AS body FROM (SELECT DISTINCT dst AS vid FROM graph_geo_arcs) GROUP BY vid % 8) p,
                LATERAL payload_rows(p.body) r"""
    )


@query(
    "g_kron_degrees",
    """SELECT degree, count(*) AS vertices FROM (SELECT vid, count(*) AS degree FROM (
  SELECT CAST(p AS VARCHAR) || ' page' AS vid FROM (SELECT DISTINCT page_id AS p, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)
  UNION ALL SELECT href FROM (SELECT DISTINCT page_id AS p, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)) GROUP BY vid) GROUP BY degree""",
)
def g_kron_degrees(spark, d):
    """Degrees of the pages' links, whose targets are few hubs."""
    from subgraph_engine.prepare import degrees

    return degrees(graphs.page_links(spark, d)).groupBy("degree").agg(F.count(F.lit(1)).alias("vertices"))
