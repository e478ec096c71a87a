"""The test graphs on the given tables, as DataFrames and as the SQL that defines the same edges.

Ids of different entities are kept apart by ``key * 4 + tag`` (order 0, customer 1, part 2, supplier 3).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .model import Graph

ORDER, CUSTOMER, PART, SUPPLIER = 0, 1, 2, 3


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def h60(text: Column) -> Column:
    """An id of a string: the first 60 bits of its MD5."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def _vid(c: str, tag: int) -> Column:
    return F.col(c) * 4 + tag


def trade_pairs(spark, d) -> DataFrame:
    rows = table(spark, d, "lineitem").select(_vid("l_partkey", PART).alias("src"), _vid("l_suppkey", SUPPLIER).alias("dst"))
    return rows.groupBy("src", "dst").agg(F.count("*").alias("weight"))


def cust_pairs(spark, d) -> DataFrame:
    lines = table(spark, d, "lineitem").where("l_quantity >= 48").select("l_orderkey", "l_partkey", "l_linenumber")
    rows = lines.join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return rows.groupBy(_vid("o_custkey", CUSTOMER).alias("src"), _vid("l_partkey", PART).alias("dst")).agg(F.min("l_linenumber").cast("long").alias("weight"))


def order_pairs(spark, d) -> DataFrame:
    lines = table(spark, d, "lineitem").where("l_quantity >= 49")
    return lines.groupBy(_vid("l_orderkey", ORDER).alias("src"), _vid("l_partkey", PART).alias("dst")).agg(F.min("l_linenumber").cast("long").alias("weight"))


def cycle_edges(spark, d, where: str) -> DataFrame:
    lines = table(spark, d, "lineitem").where(where).join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    ids = lines.select(_vid("o_custkey", CUSTOMER).alias("c"), _vid("l_suppkey", SUPPLIER).alias("s"), _vid("l_partkey", PART).alias("p"))
    both = F.array(*[F.struct(F.col(a).alias("src"), F.col(b).alias("dst")) for a, b in (("c", "s"), ("s", "p"), ("p", "c"))])
    return ids.select(F.inline(both)).distinct().withColumn("weight", F.lit(1).cast("long"))


def session_edges(spark, d) -> DataFrame:
    by = Window.partitionBy("user_id").orderBy("ts", "event_id")
    rows = table(spark, d, "events").select("event_id", F.lead("event_id").over(by).alias("dst"), F.expr("timestampdiff(SECOND, ts, lead(ts) over (partition by user_id order by ts, event_id))").alias("weight"))
    return rows.where("dst IS NOT NULL").select(F.col("event_id").alias("src"), "dst", F.col("weight").cast("long"))


def user_edges(spark, d) -> DataFrame:
    by = Window.partitionBy("event_type").orderBy("ts", "event_id")
    rows = table(spark, d, "events").select(F.col("user_id").alias("src"), F.lead("user_id").over(by).alias("dst"))
    return rows.where("dst IS NOT NULL AND src <> dst").groupBy("src", "dst").agg(F.count("*").alias("weight"))


def reply_edges(spark, d) -> DataFrame:
    rows = table(spark, d, "conversations").select((F.col("conv_id") * 16 + F.col("turn")).alias("src"), "conv_id", "turn")
    last = Window.partitionBy("conv_id").orderBy("turn")
    return rows.select("src", F.lead("src").over(last).alias("dst")).where("dst IS NOT NULL").withColumn("weight", F.lit(1).cast("long"))


def region_edges(spark, d) -> DataFrame:
    """Root to regions, to nations, to customers and suppliers."""
    t = lambda n: table(spark, d, n)
    long = lambda e: F.expr(f"cast({e} as long)")
    parts = [
        t("region").select(long("0").alias("src"), long("8 * r_regionkey + 1").alias("dst")),
        t("nation").select(long("8 * n_regionkey + 1").alias("src"), long("8 * n_nationkey + 2").alias("dst")),
        t("customer").select(long("8 * c_nationkey + 2").alias("src"), long("8 * c_custkey + 3").alias("dst")),
        t("supplier").select(long("8 * s_nationkey + 2").alias("src"), long("8 * s_suppkey + 4").alias("dst")),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.withColumn("weight", F.lit(1).cast("long"))


def page_links(spark, d) -> DataFrame:
    """(page_id, host, path) of every root-relative link."""
    pages = table(spark, d, "pages")
    host = F.regexp_extract("url", r"^https?://([^/]+)", 1)
    return pages.select("page_id", host.alias("host"), F.explode(F.regexp_extract_all("html", F.lit(r'href="(/[^"]*)"'), F.lit(1))).alias("path"))


def web_edges(spark, d) -> DataFrame:
    links = page_links(spark, d).select(F.col("page_id").alias("src"), h60(F.concat("host", "path")).alias("dst")).distinct()
    return links.withColumn("weight", F.lit(1).cast("long"))


def webbip_pairs(spark, d) -> DataFrame:
    links = page_links(spark, d).select(F.col("page_id").alias("src"), h60(F.col("path")).alias("dst")).distinct()
    return links.withColumn("weight", F.lit(1).cast("long"))


def _line_holders(spark, d, length: int) -> DataFrame:
    lines = table(spark, d, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.char_length("line") >= length)
    return lines.select("doc_id", F.md5(F.col("line").cast("binary")).alias("line")).distinct()


def copy_links(spark, d, length: int = 40) -> DataFrame:
    """Each document with the smallest one that shares a line of at least ``length`` characters with it.

    A line gives one link a holder, however many hold it: components are those of all pairs, without the pairs.
    """
    ids = _line_holders(spark, d, length)
    first = ids.groupBy("line").agg(F.min("doc_id").alias("src"))
    return ids.join(first, "line").where("src < doc_id").groupBy("src", F.col("doc_id").alias("dst")).agg(F.count("*").alias("weight"))


def _near_in_tiles(key: tuple, rows: pa.Table, least: float) -> pa.Table:
    """(src, dst, cos) of the pairs between the two tiles of the key, or inside one, of at least ``least``.

    A matrix product finds candidates; their cosines are then summed component by component, in order.
    """
    ids, tile = rows["vec_id"].to_numpy(), rows["tile"].to_numpy()
    e = rows["e"].combine_chunks().flatten().to_numpy().reshape(len(ids), -1)
    square = np.zeros(len(ids))
    for k in range(e.shape[1]):
        square += e[:, k] * e[:, k]
    norm = np.sqrt(square)
    one, two = (np.flatnonzero(tile == t.as_py()) for t in key[2:])
    out = []
    for at in range(0, len(one), 512):
        part = one[at : at + 512]
        scale = norm[part][:, None] * norm[two][None, :]
        i, j = np.nonzero(e[part] @ e[two].T >= (least - 1e-9) * scale)
        i, j = part[i], two[j]
        if key[2] != key[3]:  # inside one tile both orders of a pair are found, so one is kept
            i, j = np.where(ids[i] < ids[j], i, j), np.where(ids[i] < ids[j], j, i)
        kept = ids[i] < ids[j]
        i, j = i[kept], j[kept]
        dot = np.zeros(len(i))
        for k in range(e.shape[1]):
            dot += e[i, k] * e[j, k]
        cos = dot / (norm[i] * norm[j])
        near = cos >= least
        out.append((ids[i][near], ids[j][near], cos[near]))
    cols = [np.concatenate([x[c] for x in out]) if out else np.zeros(0, kind) for c, kind in enumerate((np.int64, np.int64, np.float64))]
    return pa.table({"src": pa.array(cols[0], pa.int64()), "dst": pa.array(cols[1], pa.int64()), "cos": pa.array(cols[2], pa.float64())})


def knn_pairs(spark, d, least: float = 0.3, tile: int = 2000) -> DataFrame:
    """Pairs of vectors of one label with a cosine of at least ``least``, all compared: tiles of some ``tile`` vectors of
    a label meet two at a time.

    Vectors that are null, zero or hold null or non-finite components have no cosine; lengths that differ don't meet.
    """
    v = table(spark, d, "embeddings").select(F.col("vec_id").cast("long").alias("vec_id"), "label", F.col("embedding").cast("array<double>").alias("e"))
    sound = F.forall("e", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("e", lambda x: x != 0)
    v = v.where(F.col("label").isNotNull() & sound).withColumn("dims", F.size("e"))
    many = v.groupBy("label", "dims").agg(F.ceil(F.count("*") / tile).cast("int").alias("tiles"))
    dealt = v.join(F.broadcast(many), ["label", "dims"]).withColumn("tile", F.pmod(F.xxhash64("vec_id"), "tiles").cast("int"))
    met = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    met = met.select("vec_id", "e", "tile", "label", "dims", F.least("tile", "other").alias("a"), F.greatest("tile", "other").alias("b"))
    found = met.groupBy("label", "dims", "a", "b").applyInArrow(lambda key, rows: _near_in_tiles(key, rows, least), "src long, dst long, cos double")
    return found.select("src", "dst", F.round(F.col("cos") * 1e6).cast("long").alias("weight"))


PAIRS = {"trade": trade_pairs, "cust": cust_pairs, "order": order_pairs, "webbip": webbip_pairs, "copy": copy_links, "knn": knn_pairs}
DIRECTED = {
    "cycle": lambda s, d: cycle_edges(s, d, "l_returnflag = 'R'"),
    "cycle_sparse": lambda s, d: cycle_edges(s, d, "l_quantity >= 50"),
    "session": session_edges, "user": user_edges, "reply": reply_edges, "region": region_edges, "web": web_edges,
}


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """One of the graphs by name; undirected ones have both directions of each pair."""
    if name in PAIRS:
        return Graph.of(PAIRS[name](spark, sf_dir), symmetric=True)
    if name == "web":
        edges = web_edges(spark, sf_dir)
        return Graph.of(edges, vertices=table(spark, sf_dir, "pages").select(F.col("page_id").alias("vid")), complete=False)
    return Graph.of(DIRECTED[name](spark, sf_dir))


# ---------------------------------------------------------------- the same edges in SQL

_H60 = "('0x' || substr(md5({}), 1, 15))::BIGINT"
_CYCLE = """SELECT DISTINCT unnest([c, s, p]) AS src, unnest([s, p, c]) AS dst, 1::BIGINT AS weight FROM
 (SELECT o_custkey * 4 + 1 AS c, l_suppkey * 4 + 3 AS s, l_partkey * 4 + 2 AS p FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE {})"""
_LINKS = """SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS path FROM pages"""

PAIR_SQL = {
    "trade": "SELECT l_partkey * 4 + 2 AS src, l_suppkey * 4 + 3 AS dst, count(*)::BIGINT AS weight FROM lineitem GROUP BY 1, 2",
    "cust": "SELECT o_custkey * 4 + 1 AS src, l_partkey * 4 + 2 AS dst, min(l_linenumber)::BIGINT AS weight FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_quantity >= 48 GROUP BY 1, 2",
    "order": "SELECT l_orderkey * 4 AS src, l_partkey * 4 + 2 AS dst, min(l_linenumber)::BIGINT AS weight FROM lineitem WHERE l_quantity >= 49 GROUP BY 1, 2",
    "webbip": f"SELECT DISTINCT page_id AS src, {_H60.format('path')} AS dst, 1::BIGINT AS weight FROM ({_LINKS})",
    "copy": """SELECT low AS src, doc_id AS dst, count(*)::BIGINT AS weight FROM l JOIN k USING (line) WHERE low < doc_id GROUP BY 1, 2""",
    "knn": """SELECT a.vec_id AS src, b.vec_id AS dst, round(1e6 * list_cosine_similarity(a.e, b.e))::BIGINT AS weight
 FROM (SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings) a JOIN (SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings) b
 ON a.label = b.label AND a.vec_id < b.vec_id WHERE list_cosine_similarity(a.e, b.e) >= 0.3""",
}
PAIR_SQL["copy"] = f"""WITH l AS (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 40),
 k AS (SELECT line, min(doc_id) AS low FROM l GROUP BY line) {PAIR_SQL["copy"]}"""
EDGE_SQL = {
    "cycle": _CYCLE.format("l_returnflag = 'R'"),
    "cycle_sparse": _CYCLE.format("l_quantity >= 50"),
    "session": """SELECT event_id AS src, dst, weight FROM (SELECT event_id, lead(event_id) OVER w AS dst, date_diff('microsecond', ts, lead(ts) OVER w) // 1000000 AS weight
 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE dst IS NOT NULL""",
    "user": """SELECT src, dst, count(*)::BIGINT AS weight FROM (SELECT user_id AS src, lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS dst FROM events)
 WHERE dst IS NOT NULL AND src <> dst GROUP BY 1, 2""",
    "reply": """SELECT src, dst, 1::BIGINT AS weight FROM (SELECT 16 * conv_id + turn AS src, lead(16 * conv_id + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations) WHERE dst IS NOT NULL""",
    "region": """SELECT 0::BIGINT AS src, (8 * r_regionkey + 1)::BIGINT AS dst, 1::BIGINT AS weight FROM region UNION ALL SELECT 8 * n_regionkey + 1, 8 * n_nationkey + 2, 1 FROM nation
 UNION ALL SELECT 8 * c_nationkey + 2, 8 * c_custkey + 3, 1 FROM customer UNION ALL SELECT 8 * s_nationkey + 2, 8 * s_suppkey + 4, 1 FROM supplier""",
    "web": f"SELECT DISTINCT page_id AS src, {_H60.format('host || path')} AS dst, 1::BIGINT AS weight FROM ({_LINKS})",
}


def edge_sql(name: str) -> str:
    """SQL of (src, dst, weight) with both directions where the graph is undirected."""
    if name in PAIR_SQL:
        return f"SELECT src, dst, weight FROM ({PAIR_SQL[name]}) UNION SELECT dst, src, weight FROM ({PAIR_SQL[name]})"
    return EDGE_SQL[name]
