"""Surrounding relational operators, each one query on the given tables with its SQL."""

from __future__ import annotations

import uuid

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..graphs import PAIR_SQL, PAIRS, edge_sql, graph, h60, page_links, region_edges, table
from ..plans.hints import Connector, GroupBy
from ..runtime.session import fresh_session, settings, shared_folder

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str):
    """Register a query under its function's name with its SQL."""

    def add(f):
        QUERIES[f.__name__] = f
        SQL[f.__name__] = sql
        return f

    return add


_CUST = f"({PAIR_SQL['cust']})"
_DEG = f"(SELECT src AS vid, count(*)::BIGINT AS degree FROM ({edge_sql('cust')}) GROUP BY 1)"


def _n():
    return F.count("*").cast("long")



def _degree(spark, d) -> DataFrame:
    return graph(spark, d, "cust").edges.groupBy(F.col("src").alias("vid")).agg(_n().alias("degree"))


@query(f"SELECT 'part' AS side, count(*)::BIGINT AS n, sum(weight)::BIGINT AS lines FROM ({PAIR_SQL['trade']})")
def o_scan_edges(spark, d):
    return PAIRS["trade"](spark, d).agg(_n().alias("n"), F.sum("weight").alias("lines")).select(F.lit("part").alias("side"), "n", "lines")


@query(f"SELECT vid, degree FROM {_DEG} JOIN customer ON vid = c_custkey * 4 + 1 WHERE degree > 2 AND c_mktsegment = 'BUILDING'")
def o_filter_active(spark, d):
    some = table(spark, d, "customer").where("c_mktsegment = 'BUILDING'").select((F.col("c_custkey") * 4 + 1).alias("vid"))
    return _degree(spark, d).where("degree > 2").join(some, "vid")


@query(f"SELECT src AS vid, dst, weight * 2 AS cost FROM {_CUST}")
def o_project_fields(spark, d):
    rows = PAIRS["cust"](spark, d).select(F.struct(F.col("src").alias("vid"), "dst", (F.col("weight") * 2).alias("cost")).alias("x"))
    return rows.select("x.vid", "x.dst", "x.cost")


_MSG = "(SELECT l_suppkey AS k, count(*)::BIGINT AS n FROM lineitem WHERE l_quantity >= 50 GROUP BY 1)"


def _msgs(spark, d) -> DataFrame:
    return table(spark, d, "lineitem").where("l_quantity >= 50").groupBy(F.col("l_suppkey").alias("k")).agg(_n().alias("n"))


def _suppliers(spark, d) -> DataFrame:
    return table(spark, d, "supplier").select("s_suppkey", F.col("s_name"))


@query(f"SELECT s_suppkey, s_name, n FROM supplier JOIN {_MSG} ON s_suppkey = k")
def o_join_inner(spark, d):
    return _suppliers(spark, d).join(_msgs(spark, d), F.col("s_suppkey") == F.col("k")).select("s_suppkey", "s_name", "n")


@query(f"SELECT s_suppkey, s_name, coalesce(n, 0) AS n FROM supplier LEFT JOIN {_MSG} ON s_suppkey = k")
def o_join_left(spark, d):
    return _suppliers(spark, d).join(_msgs(spark, d), F.col("s_suppkey") == F.col("k"), "left").select("s_suppkey", "s_name", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


@query(f"SELECT coalesce(s_suppkey, k) AS vid, s_name, n FROM (SELECT * FROM supplier WHERE s_suppkey % 2 = 0) FULL JOIN {_MSG} ON s_suppkey = k")
def o_join_full(spark, d):
    return _suppliers(spark, d).where("s_suppkey % 2 = 0").join(_msgs(spark, d), F.col("s_suppkey") == F.col("k"), "full_outer").select(F.coalesce("s_suppkey", "k").alias("vid"), "s_name", "n")


@query("SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def o_join_broadcast(spark, d):
    small = table(spark, d, "nation").join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(spark, d, "customer").join(F.broadcast(small), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name")


@query("SELECT o_custkey, count(*)::BIGINT AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def o_join_shuffle_hash(spark, d):
    lines, orders = table(spark, d, "lineitem").select("l_orderkey"), table(spark, d, "orders").select("o_orderkey", "o_custkey")
    return lines.join(orders.hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(_n().alias("n"))


@query(f"SELECT c_custkey FROM customer WHERE c_custkey * 4 + 1 IN (SELECT src FROM {_CUST})")
def o_join_semi(spark, d):
    return table(spark, d, "customer").select("c_custkey", (F.col("c_custkey") * 4 + 1).alias("src")).join(PAIRS["cust"](spark, d), "src", "left_semi").select("c_custkey")


@query(f"SELECT c_custkey FROM customer WHERE c_custkey * 4 + 1 NOT IN (SELECT src FROM {_CUST})")
def o_join_anti(spark, d):
    return table(spark, d, "customer").select("c_custkey", (F.col("c_custkey") * 4 + 1).alias("src")).join(PAIRS["cust"](spark, d), "src", "left_anti").select("c_custkey")


@query("SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) < 500")
def o_join_theta(spark, d):
    s = table(spark, d, "supplier").select("s_nationkey", "s_suppkey", "s_acctbal")
    return s.toDF("k", "a", "x").join(s.toDF("k", "b", "y"), "k").where("a < b AND abs(x - y) < 500").select("a", "b")


@query("""SELECT p.event_id AS purchase, e.event_id AS event FROM events p JOIN events e ON p.user_id = e.user_id
 AND p.event_type = 'purchase' AND e.ts > p.ts AND e.ts <= p.ts + INTERVAL 1 HOUR""")
def o_join_range(spark, d):
    """Range join by hour buckets: a purchase is put in its hour and the next, so the join is an equi-join."""
    e = table(spark, d, "events").select("event_id", "user_id", "event_type", "ts", F.expr("cast(floor(unix_micros(cast(ts as timestamp)) / 3600000000) as long)").alias("hour"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("pts"), F.explode(F.array(F.col("hour"), F.col("hour") + 1)).alias("hour"))
    return p.join(e.select(F.col("event_id").alias("event"), "user_id", "ts", "hour"), ["user_id", "hour"]).where("ts > pts AND ts <= pts + INTERVAL 1 HOUR").select("purchase", "event")


@query("""SELECT p.event_id AS purchase, c.event_id AS click FROM (SELECT * FROM events WHERE event_type = 'purchase') p
 ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND p.ts > c.ts""")
def o_join_asof(spark, d):
    by = Window.partitionBy("user_id").orderBy("ts", "late").rowsBetween(Window.unboundedPreceding, -1)
    e = table(spark, d, "events").where("event_type IN ('click', 'purchase')").withColumn("late", F.when(F.col("event_type") == "click", 1).otherwise(0))
    seen = e.withColumn("click", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(by))
    return seen.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "click")


@query(f"""WITH e AS ({edge_sql('cust')}) SELECT a.src AS vid, count(DISTINCT b.dst)::BIGINT AS n FROM e a JOIN e b ON a.dst = b.src WHERE a.src <> b.dst GROUP BY 1""")
def o_join_self_2hop(spark, d):
    e = graph(spark, d, "cust").edges.select("src", "dst")
    return e.toDF("vid", "m").join(e.toDF("m", "far"), "m").where("vid <> far").select("vid", "far").distinct().groupBy("vid").agg(_n().alias("n"))


@query("SELECT l_partkey, count(*)::BIGINT AS n FROM lineitem GROUP BY 1")
def o_agg_hash(spark, d):
    return table(spark, d, "lineitem").groupBy("l_partkey").agg(_n().alias("n"))


@query("SELECT l_partkey, count(*)::BIGINT AS n FROM lineitem GROUP BY 1")
def o_agg_sort(spark, d):
    with settings(spark, **{"spark.sql.execution.replaceHashWithSortAgg": "true"}):
        return table(spark, d, "lineitem").select("l_partkey").repartition("l_partkey").sortWithinPartitions("l_partkey").groupBy("l_partkey").agg(_n().alias("n"))


@query("SELECT l_partkey, count(DISTINCT l_suppkey)::BIGINT AS n FROM lineitem GROUP BY 1")
def o_agg_distinct(spark, d):
    return table(spark, d, "lineitem").groupBy("l_partkey").agg(F.count_distinct("l_suppkey").alias("n"))


@query("SELECT l_orderkey, bool_and(l_linestatus = 'F') AS done, bool_or(l_returnflag = 'R') AS returned FROM lineitem GROUP BY 1")
def o_agg_bool(spark, d):
    return table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.bool_and(F.col("l_linestatus") == "F").alias("done"), F.bool_or(F.col("l_returnflag") == "R").alias("returned"))


@query(f"SELECT src AS vid, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS near FROM ({edge_sql('cust')}) GROUP BY 1")
def o_agg_collect(spark, d):
    rows = graph(spark, d, "cust").edges.groupBy(F.col("src").alias("vid")).agg(F.array_sort(F.collect_set("dst")).alias("x"))
    return rows.select("vid", F.array_join(F.transform("x", lambda v: v.cast("string")), ",").alias("near"))


@query(f"SELECT round(quantile_cont(degree, 0.5), 6)::DOUBLE AS p50, round(quantile_cont(degree, 0.95), 6)::DOUBLE AS p95 FROM {_DEG}")
def o_agg_percentile(spark, d):
    return _degree(spark, d).agg(F.round(F.percentile("degree", F.lit(0.5)), 6).alias("p50"), F.round(F.percentile("degree", F.lit(0.95)), 6).alias("p95"))


@query(f"SELECT src AS vid, weight, dst FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY weight DESC, dst DESC) AS r FROM ({edge_sql('cust')})) WHERE r = 1")
def o_agg_max_by(spark, d):
    rows = graph(spark, d, "cust").edges.groupBy(F.col("src").alias("vid")).agg(F.max(F.struct("weight", "dst")).alias("x"))
    return rows.select("vid", "x.weight", "x.dst")


_GEO = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _geo(spark, d) -> DataFrame:
    return table(spark, d, "customer").join(table(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))


@query(f"SELECT r_name, c_mktsegment, count(*)::BIGINT AS n {_GEO} GROUP BY CUBE (r_name, c_mktsegment)")
def o_cube(spark, d):
    return _geo(spark, d).cube("r_name", "c_mktsegment").agg(_n().alias("n"))


@query(f"SELECT r_name, n_name, count(*)::BIGINT AS n {_GEO} GROUP BY ROLLUP (r_name, n_name)")
def o_rollup(spark, d):
    return _geo(spark, d).rollup("r_name", "n_name").agg(_n().alias("n"))


@query(f"SELECT r_name, c_mktsegment, count(*)::BIGINT AS n {_GEO} GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")
def o_grouping_sets(spark, d):
    return _geo(spark, d).groupingSets([["r_name"], ["c_mktsegment"], []], "r_name", "c_mktsegment").agg(_n().alias("n"))


@query("""SELECT user_id, count(*) FILTER (event_type = 'click')::BIGINT AS click, count(*) FILTER (event_type = 'view')::BIGINT AS "view",
 count(*) FILTER (event_type = 'purchase')::BIGINT AS purchase FROM events GROUP BY 1""")
def o_pivot(spark, d):
    return table(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "view", "purchase"]).agg(F.count("event_id")).na.fill(0)


@query(f"""SELECT vid, degree, rank() OVER w::BIGINT AS r, dense_rank() OVER w::BIGINT AS dr, ntile(4) OVER (PARTITION BY vid % 4 ORDER BY degree DESC, vid)::BIGINT AS nt
 FROM {_DEG} WINDOW w AS (PARTITION BY vid % 4 ORDER BY degree DESC)""")
def o_win_rank(spark, d):
    w = Window.partitionBy(F.col("vid") % 4).orderBy(F.desc("degree"))
    return _degree(spark, d).select("vid", "degree", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(Window.partitionBy(F.col("vid") % 4).orderBy(F.desc("degree"), "vid")).cast("long").alias("nt"))


@query("SELECT event_id, lead(event_id) OVER w AS nxt, lag(event_id) OVER w AS prv FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def o_win_chain(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, d, "events").select("event_id", F.lead("event_id").over(w).alias("nxt"), F.lag("event_id").over(w).alias("prv"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 4 PRECEDING), 4) AS s FROM events")
def o_win_frame_rows(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    return table(spark, d, "events").select("event_id", F.round(F.sum("value").over(w), 4).alias("s"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW)::BIGINT AS n FROM events")
def o_win_frame_range(spark, d):
    e = table(spark, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.count("*").over(w).alias("n"))


@query(f"SELECT vid, degree FROM {_DEG} ORDER BY degree DESC, vid LIMIT 20")
def o_topk_rank(spark, d):
    return _degree(spark, d).orderBy(F.desc("degree"), "vid").limit(20)


@query(f"SELECT src, dst, weight FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY weight DESC, dst) AS r FROM ({edge_sql('cust')})) WHERE r <= 3")
def o_topk_group(spark, d):
    w = Window.partitionBy("src").orderBy(F.desc("weight"), "dst")
    return graph(spark, d, "cust").edges.withColumn("r", F.row_number().over(w)).where("r <= 3").select("src", "dst", "weight")


@query(f"SELECT src, dst, weight, row_number() OVER (ORDER BY weight DESC, src, dst)::BIGINT AS at FROM {_CUST}")
def o_sort_global(spark, d):
    """A global order with positions: range-partitioned sort, one offset a range, positions inside each range."""
    rows = PAIRS["cust"](spark, d).repartitionByRange(8, F.desc("weight"), F.asc("src"), F.asc("dst")).withColumn("p", F.spark_partition_id())
    rows = rows.checkpoint() if shared_folder(spark) else rows
    sums = rows.groupBy("p").agg(F.count("*").alias("m"))
    before = sums.select("p", F.coalesce(F.sum("m").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inside = Window.partitionBy("p").orderBy(F.desc("weight"), "src", "dst")
    return rows.join(F.broadcast(before), "p").select("src", "dst", "weight", (F.col("base") + F.row_number().over(inside)).cast("long").alias("at"))


_R = "SELECT l_partkey AS p, l_suppkey AS s FROM lineitem WHERE l_returnflag = 'R'"
_Q = "SELECT l_partkey AS p, l_suppkey AS s FROM lineitem WHERE l_quantity >= 48"


def _sets(spark, d) -> tuple[DataFrame, DataFrame]:
    lines = table(spark, d, "lineitem")
    pick = lambda where: lines.where(where).select(F.col("l_partkey").alias("p"), F.col("l_suppkey").alias("s"))
    return pick("l_returnflag = 'R'"), pick("l_quantity >= 48")


@query(f"{_R} UNION {_Q}")
def o_union_edges(spark, d):
    a, b = _sets(spark, d)
    return a.unionByName(b).distinct()


@query(f"{_R} INTERSECT {_Q}")
def o_intersect_edges(spark, d):
    a, b = _sets(spark, d)
    return a.intersect(b)


@query(f"{_R} EXCEPT {_Q}")
def o_except_edges(spark, d):
    a, b = _sets(spark, d)
    return a.subtract(b)


@query(f"{_R} EXCEPT ALL {_Q}")
def o_except_all_edges(spark, d):
    a, b = _sets(spark, d)
    return a.exceptAll(b)


@query(f"{_R} INTERSECT ALL {_Q}")
def o_intersect_all_edges(spark, d):
    a, b = _sets(spark, d)
    return a.intersectAll(b)


@query("""SELECT page_id, host, path, length(path)::BIGINT AS n FROM (SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host,
 unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS path FROM pages)""")
def o_str_links(spark, d):
    return page_links(spark, d).withColumn("n", F.char_length("path").cast("long"))


@query("SELECT a.page_id AS a, b.page_id AS b, levenshtein(a.url, b.url)::BIGINT AS far FROM pages a JOIN pages b ON b.page_id = a.page_id + 1")
def o_str_distance(spark, d):
    """Edits between the addresses of pages with successive numbers."""
    pages = table(spark, d, "pages")
    rows = pages.select(F.col("page_id").alias("a"), "url").join(pages.select(F.col("page_id").alias("b"), F.col("url").alias("next"), (F.col("page_id") - 1).alias("a")), "a")
    return rows.select("a", "b", F.levenshtein("url", "next").cast("long").alias("far"))


@query("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, hour(ts)::BIGINT AS hour, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def o_date_bucket(spark, d):
    return table(spark, d, "events").groupBy(F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd").alias("day"), F.hour("ts").cast("long").alias("hour")).agg(_n().alias("n"))


@query(f"SELECT floor(log2(degree))::BIGINT AS bucket, count(*)::BIGINT AS n, round(avg(degree), 6) AS mean FROM {_DEG} GROUP BY 1")
def o_math(spark, d):
    return _degree(spark, d).groupBy(F.floor(F.log2("degree")).cast("long").alias("bucket")).agg(_n().alias("n"), F.round(F.avg("degree"), 6).alias("mean"))


@query(f"""SELECT vid, list_sum(list_transform(x, lambda v: v % 7))::BIGINT AS s, len(list_filter(x, lambda v: v % 2 = 0))::BIGINT AS even, array_to_string(x[1:3], ',') AS head
 FROM (SELECT src AS vid, list_sort(list(dst)) AS x FROM ({edge_sql('cust')}) GROUP BY 1)""")
def o_array_hof(spark, d):
    rows = graph(spark, d, "cust").edges.groupBy(F.col("src").alias("vid")).agg(F.array_sort(F.collect_list("dst")).alias("x"))
    return rows.select("vid", F.aggregate("x", F.lit(0).cast("long"), lambda s, v: s + v % 7).alias("s"), F.size(F.filter("x", lambda v: v % 2 == 0)).cast("long").alias("even"), F.array_join(F.transform(F.slice("x", 1, 3), lambda v: v.cast("string")), ",").alias("head"))


@query("SELECT user_id, count(*) FILTER (event_type = 'click')::BIGINT AS clicks, count(DISTINCT event_type)::BIGINT AS kinds FROM events GROUP BY 1")
def o_map_attr(spark, d):
    each = table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = each.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).cast("long").alias("clicks"), F.size("m").cast("long").alias("kinds"))


@query("SELECT event_type, sum((props->>'$.k')::BIGINT)::BIGINT AS k, count(*)::BIGINT AS n FROM events GROUP BY 1")
def o_json_props(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k"), _n().alias("n"))


@query("SELECT page_id, ('0x' || substr(md5(url), 1, 15))::BIGINT AS id FROM pages")
def o_hash_ids(spark, d):
    return table(spark, d, "pages").select("page_id", h60(F.col("url")).alias("id"))


@query(f"SELECT src, dst, weight FROM ({PAIR_SQL['knn']})")
def o_cosine(spark, d):
    return PAIRS["knn"](spark, d)


@query("SELECT l_partkey, sum(l_extendedprice::DECIMAL(18,2))::DOUBLE AS total FROM lineitem GROUP BY 1")
def o_decimal_sum(spark, d):
    return table(spark, d, "lineitem").groupBy("l_partkey").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double").alias("total"))


@query("""WITH a AS (SELECT nullif(c_nationkey % 5, 0) AS k, count(*)::BIGINT AS n FROM customer GROUP BY 1), b AS (SELECT nullif(s_nationkey % 5, 0) AS k, count(*)::BIGINT AS m FROM supplier GROUP BY 1)
 SELECT coalesce(a.k, -1)::BIGINT AS k, n, m FROM a JOIN b ON a.k IS NOT DISTINCT FROM b.k""")
def o_null_semantics(spark, d):
    a = table(spark, d, "customer").groupBy(F.nullif(F.col("c_nationkey") % 5, F.lit(0)).alias("k")).agg(_n().alias("n"))
    b = table(spark, d, "supplier").groupBy(F.nullif(F.col("s_nationkey") % 5, F.lit(0)).alias("k2")).agg(_n().alias("m"))
    return a.join(b, F.col("k").eqNullSafe(F.col("k2"))).select(F.coalesce("k", F.lit(-1)).cast("long").alias("k"), "n", "m")


@query(f"""WITH RECURSIVE e AS ({edge_sql('region')}), t(vid, path, depth) AS (SELECT dst, 'root/r' || dst // 8, 1 FROM e WHERE src = 0
 UNION ALL SELECT e.dst, path || '/' || ['r', 'n', 'c', 's'][e.dst % 8] || e.dst // 8, depth + 1 FROM t JOIN e ON t.vid = e.src)
 SELECT ['r', 'n', 'c', 's'][vid % 8] || vid // 8 AS id, path, depth::BIGINT AS depth FROM t""")
def o_sql_recursive(spark, d):
    """Paths from the root to all regions, nations, customers and suppliers; nothing is below the last two."""
    own = fresh_session(spark)
    own.conf.set("spark.sql.cteRecursionRowLimit", "-1")  # else Spark raises beyond a million rows
    region_edges(own, d).createOrReplaceTempView("bspflow_region")
    return own.sql("""WITH RECURSIVE t(vid, path, depth) AS (
        SELECT dst, concat('root/r', dst div 8), 1 FROM bspflow_region WHERE src = 0
        UNION ALL SELECT e.dst, concat(path, '/', elt(e.dst % 8, 'r', 'n', 'c', 's'), e.dst div 8), depth + 1 FROM t JOIN bspflow_region e ON t.vid = e.src WHERE t.vid % 8 < 3)
        SELECT concat(elt(vid % 8, 'r', 'n', 'c', 's'), vid div 8) AS id, path, cast(depth AS BIGINT) AS depth FROM t""")


@query(f"SELECT vid % 4 AS tag, count(*)::BIGINT AS n, sum(degree)::BIGINT AS total FROM {_DEG} GROUP BY 1")
def o_sink_partitioned(spark, d):
    """Written by tag and read back; only the columns asked for are read."""
    path = f"{shared_folder(spark)}/sink-{uuid.uuid4().hex}"
    _degree(spark, d).withColumn("tag", F.col("vid") % 4).write.partitionBy("tag").parquet(path)
    return spark.read.parquet(path).groupBy(F.col("tag").cast("long").alias("tag")).agg(_n().alias("n"), F.sum("degree").alias("total"))


@query(f"SELECT src AS vid, min(dst) AS payload FROM ({edge_sql('cust')}) GROUP BY 1")
def o_combine_merge(spark, d):
    from ..plans.combine import MIN, combine

    raw = graph(spark, d, "cust").edges.select(F.col("src").alias("vid"), F.col("dst").alias("payload"))
    return combine(raw, MIN, GroupBy.HASH, Connector.MERGE, 8)


@query("SELECT page_id, lower(regexp_replace(url, '^https?://', '')) AS url FROM pages")
def o_udf_pandas(spark, d):
    from ..functions.udf import canonical_url

    return table(spark, d, "pages").select("page_id", canonical_url("url").alias("url"))


@query(f"SELECT src AS vid, min(dst) AS low FROM ({edge_sql('cust')}) GROUP BY 1")
def o_udaf(spark, d):
    from ..functions.udf import tree_min

    return graph(spark, d, "cust").edges.groupBy(F.col("src").alias("vid")).agg(tree_min("dst").alias("low"))


@query("SELECT item_id, i::BIGINT AS i, substr(text, i + 1, 12) AS kmer FROM (SELECT item_id, text, unnest(range(0, length(text) - 11)) AS i FROM benchmark WHERE length(text) >= 12)")
def o_udtf(spark, d):
    from ..functions.udf import register

    register(spark)
    table(spark, d, "benchmark").createOrReplaceTempView("bspflow_benchmark")
    return spark.sql("SELECT item_id, k.i, k.kmer FROM bspflow_benchmark, LATERAL bspflow_kmers(text, 12) AS k")


@query("SELECT item_id, i::BIGINT AS i, substr(text, i + 1, 12) AS kmer FROM (SELECT item_id, text, unnest(range(0, length(text) - 11)) AS i FROM benchmark WHERE length(text) >= 12)")
def o_str_kmers(spark, d):
    """What ``o_udtf`` gives, of built-in functions."""
    at = F.posexplode(F.transform(F.sequence(F.lit(1), F.char_length("text") - 11), lambda i: F.substr(F.col("text"), i, F.lit(12))))
    return table(spark, d, "benchmark").where("char_length(text) >= 12").select("item_id", at.alias("i", "kmer")).withColumn("i", F.col("i").cast("long"))


@query(f"SELECT src, dst, CASE WHEN (src % 97, src) < (dst % 97, dst) THEN src ELSE dst END AS winner FROM {_CUST}")
def o_udf(spark, d):
    from ..functions.udf import tie_break

    return PAIRS["cust"](spark, d).select("src", "dst", tie_break("src", "dst").alias("winner"))


@query("SELECT page_id, lower(regexp_replace(url, '^https?://', '')) AS url FROM pages")
def o_udf_arrow(spark, d):
    from ..functions.udf import canonical_url_arrow

    return table(spark, d, "pages").select("page_id", canonical_url_arrow("url").alias("url"))


@query(f"SELECT src, dst, weight FROM ({edge_sql('cust')})")
def o_udtf_neighbors(spark, d):
    from ..functions.udf import register

    register(spark)
    near = F.collect_list(F.struct("dst", F.col("weight").alias("value"))).alias("edges")
    graph(spark, d, "cust").edges.groupBy("src").agg(near).createOrReplaceTempView("bspflow_nested")
    return spark.sql("SELECT src, n.dst, n.weight FROM bspflow_nested, LATERAL bspflow_neighbors(edges) AS n")


@query(f"SELECT src, dst, weight * 2 AS twice FROM {_CUST} WHERE (src + dst) % 3 = 0")
def o_map_in_arrow(spark, d):
    """A filter and a column over whole Arrow batches; rows keep no partitioning."""

    def run(batches):
        for b in batches:
            total = pa.array(pc.add(b["src"], b["dst"]).to_numpy(zero_copy_only=False) % 3)
            kept = b.filter(pc.equal(total, 0))
            yield pa.RecordBatch.from_arrays([kept["src"], kept["dst"], pc.multiply(kept["weight"], 2)], names=["src", "dst", "twice"])

    return PAIRS["cust"](spark, d).select("src", "dst", "weight").mapInArrow(run, "src long, dst long, twice long")


@query("""SELECT user_id, count(*)::BIGINT AS kinds, arg_min(event_type, (-n, event_type)) AS most FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1""")
def o_apply_in_arrow(spark, d):
    """Per user the commonest kind of event; counts fold first, so that a group has a row a kind, however busy its user."""

    def run(key, group):
        top = group.sort_by([("n", "descending"), ("event_type", "ascending")])
        return pa.table({"user_id": [key[0].as_py()], "kinds": [group.num_rows], "most": [top["event_type"][0].as_py()]}, schema=pa.schema([("user_id", pa.int64()), ("kinds", pa.int64()), ("most", pa.string())]))

    each = table(spark, d, "events").groupBy(F.col("user_id").cast("long").alias("user_id"), "event_type").agg(_n().alias("n"))
    return each.groupBy("user_id").applyInArrow(run, "user_id long, kinds long, most string")


@query(f"SELECT coalesce(s_suppkey, k)::BIGINT AS vid, s_suppkey IS NOT NULL AS known, coalesce(n, 0)::BIGINT AS n FROM (SELECT * FROM supplier WHERE s_suppkey % 2 = 0) FULL JOIN {_MSG} ON s_suppkey = k")
def o_cogroup(spark, d):
    """Delivery as a cogroup: vertices on one side, folded messages on the other, at most a row each a key."""

    def run(key, vertices, messages):
        n = messages["n"][0].as_py() if messages.num_rows else 0
        return pa.table({"vid": pa.array([key[0].as_py()], pa.int64()), "known": [vertices.num_rows > 0], "n": pa.array([n], pa.int64())})

    vertices = _suppliers(spark, d).where("s_suppkey % 2 = 0").select(F.col("s_suppkey").cast("long").alias("vid"))
    messages = _msgs(spark, d).select(F.col("k").cast("long").alias("vid"), "n")
    return vertices.groupBy("vid").cogroup(messages.groupBy("vid")).applyInArrow(run, "vid long, known boolean, n long")


@query(f"SELECT vid, degree, total FROM {_DEG} JOIN (SELECT src, sum(weight)::BIGINT AS total FROM ({edge_sql('cust')}) GROUP BY 1) ON src = vid")
def o_sink_bucketed(spark, d):
    """Vertices and edges as catalog tables bucketed by id: read back, they meet without an exchange."""
    vertices = bucketed(_degree(spark, d), 8, "vid")
    edges = bucketed(graph(spark, d, "cust").edges.withColumnRenamed("src", "vid"), 8, "vid")
    return vertices.join(edges.groupBy("vid").agg(F.sum("weight").alias("total")), "vid")


def _approx(spark, d):
    """Approximate distinct suppliers of each part; no SQL engine has the same sketch."""
    return table(spark, d, "lineitem").groupBy("l_partkey").agg(F.approx_count_distinct("l_suppkey", 0.02).alias("n"))


QUERIES["o_agg_approx"] = _approx


def bucketed(df: DataFrame, buckets: int, key: str, name: str | None = None) -> DataFrame:
    """A catalog table bucketed and sorted by ``key``, for joins without an exchange; its files are in the shared folder.

    Rows are dealt by ``key`` first: each task then writes its own buckets, instead of a file a bucket from every task.
    """
    spark, name = df.sparkSession, name or f"bspflow_{uuid.uuid4().hex}"
    dealt = df.repartition(buckets, key).write.bucketBy(buckets, key).sortBy(key)
    dealt.option("path", f"{shared_folder(spark)}/{name}").saveAsTable(name)
    return spark.table(name)


def views(spark: SparkSession, sf_dir: str, names: list[str]) -> None:
    """Temp views v_<graph> and e_<graph> for SQL users."""
    for name in names:
        g = graph(spark, sf_dir, name)
        g.vertices.createOrReplaceTempView(f"v_{name}")
        g.edges.createOrReplaceTempView(f"e_{name}")
