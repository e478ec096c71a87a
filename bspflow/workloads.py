"""Every method, variant, baseline and workload as a query over the given tables, with SQL where SQL can express it."""

from __future__ import annotations

import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .algos import assembly, compact, structure, vertex
from .baselines.systems import SYSTEMS, task
from .graphs import PAIR_SQL, PAIRS, edge_sql, graph, table
from .model import Graph
from .operators import relational
from .operators.rowprogram import RowProgram, run_rows
from .plans.combine import COUNT, LIST, MAX, MIN, SUM
from .plans.hints import Connector, GroupBy, Join, PlanHints, Store, all_plans
from .plans.logical import apply_mutations
from .program import Program, Step, deletion, insertion, letter
from .runtime.checkpoint import Checkpointer
from .runtime.loop import run
from .runtime.pipeline import Job, pipeline, run_recoverable
from .runtime.session import fresh_session, row_partitions, shared_folder
from .streaming import streams

QUERIES: dict = {}
SQL: dict[str, str] = {}

HASH = PlanHints(Join.FULL, GroupBy.HASH)
LEFT = PlanHints(Join.LEFT, GroupBy.HASH)


def _add(name: str, f, sql: str | None = None) -> None:
    QUERIES[name] = f
    if sql:
        SQL[name] = sql


# ---------------------------------------------------------------- SQL of the recurring results


def rank_sql(edges: str, steps: int = 10, vertices: str | None = None) -> str:
    v = vertices or "SELECT src AS vid FROM e0 UNION SELECT dst FROM e0"
    return f"""WITH RECURSIVE e0 AS MATERIALIZED ({edges}), v AS MATERIALIZED ({v}),
 e AS MATERIALIZED (SELECT src, dst, count(*) OVER (PARTITION BY src) AS deg FROM e0), n AS MATERIALIZED (SELECT count(*) AS n FROM v),
 t(step, vid, rank) AS (SELECT 1, vid, (1000000000000 // n)::BIGINT FROM v, n UNION ALL
  SELECT s.step + 1, v.vid, (150000000000 // n + (coalesce(m, 0) * 85) // 100)::BIGINT FROM v CROSS JOIN n CROSS JOIN (SELECT max(step) AS step FROM t HAVING max(step) < {steps}) s
  LEFT JOIN (SELECT e.dst AS vid, sum(rank // deg)::BIGINT AS m FROM t JOIN e ON e.src = t.vid GROUP BY e.dst) g ON g.vid = v.vid)
 SELECT vid, rank FROM t WHERE step = {steps}"""


def dist_sql(edges: str, start: str, cost: str = "1", rest: str = "SELECT vid, dist FROM t") -> str:
    return f"""WITH RECURSIVE e AS MATERIALIZED ({edges}), t(vid, dist) USING KEY (vid) AS (SELECT vid::BIGINT, 0::BIGINT FROM ({start}) UNION
 SELECT x.vid, x.dist FROM (SELECT e.dst AS vid, min(t.dist + {cost})::BIGINT AS dist FROM t JOIN e ON e.src = t.vid GROUP BY e.dst) x LEFT JOIN recurring.t r ON r.vid = x.vid
 WHERE r.vid IS NULL OR x.dist < r.dist) {rest}"""


def label_sql(edges: str, rest: str = "SELECT vid, label FROM t") -> str:
    return f"""WITH RECURSIVE e AS MATERIALIZED (SELECT src, dst FROM ({edges}) UNION SELECT dst, src FROM ({edges})),
 t(vid, label) USING KEY (vid) AS (SELECT src, src FROM e GROUP BY 1 UNION SELECT x.vid, x.label FROM
 (SELECT e.dst AS vid, min(t.label) AS label FROM t JOIN e ON e.src = t.vid GROUP BY e.dst) x JOIN recurring.t r ON r.vid = x.vid WHERE x.label < r.label) {rest}"""


TOP = "SELECT src AS vid FROM e GROUP BY src ORDER BY count(*) DESC, src LIMIT 1"
SSSP_CUST = dist_sql(edge_sql("cust"), TOP)


# ---------------------------------------------------------------- rank, distance, components


def _ranks(name: str, steps: int = 10, hints: PlanHints = vertex.RANK_PLAN):
    return lambda spark, d: vertex.pagerank(graph(spark, d, name), steps, fixed_point=True, hints=hints).vertices.select("vid", F.col("value").alias("rank"))


def _dists(name: str, weighted: bool = False, hints: PlanHints = vertex.SPARSE_PLAN):
    def f(spark, d) -> DataFrame:
        g = graph(spark, d, name)
        got = vertex.sssp(g, vertex.highest_degree(g), weighted, hints).vertices
        return got.where("value IS NOT NULL").select("vid", F.col("value").alias("dist"))

    return f


def _labels(name: str, hints: PlanHints = vertex.COMPONENT_PLAN):
    return lambda spark, d: vertex.connected_components(graph(spark, d, name), hints).vertices.select("vid", F.col("value").alias("label"))


for _g in ("trade", "webbip", "cycle"):
    _add(f"w_pagerank_{'web' if _g == 'webbip' else _g}", _ranks(_g), rank_sql(edge_sql(_g)))


def w_pagerank_trade_dbl(spark, d):
    got = vertex.pagerank(graph(spark, d, "trade"), 10).vertices
    return got.select("vid", F.round("value", 6).alias("rank"))


_add("w_pagerank_trade_dbl", w_pagerank_trade_dbl, rank_sql(edge_sql("trade")).replace("SELECT vid, rank FROM t", "SELECT vid, round(rank / 1e12, 6) AS rank FROM t"))


def _completed_web(spark, d) -> Graph:
    g = graph(spark, d, "web")
    return Graph.of(g.edges, vertices=g.vertices, complete=True)


def w_pagerank_dangling(spark, d):
    got = vertex.pagerank(_completed_web(spark, d), 6, dangling="redistribute").vertices
    return got.select("vid", F.round("value", 6).alias("rank"))


_add("w_pagerank_dangling", w_pagerank_dangling, f"""WITH RECURSIVE e0 AS MATERIALIZED ({edge_sql('web')}), v AS MATERIALIZED (SELECT page_id AS vid FROM pages UNION SELECT dst FROM e0),
 e AS MATERIALIZED (SELECT src, dst, count(*) OVER (PARTITION BY src) AS deg FROM e0), n AS MATERIALIZED (SELECT count(*) AS n FROM v),
 t(step, vid, rank) AS (SELECT 1, vid, 1.0::DOUBLE / n FROM v, n UNION ALL
  SELECT s.step + 1, v.vid, 0.15::DOUBLE / n + 0.85::DOUBLE * (coalesce(m, 0) + s.loose / n) FROM v CROSS JOIN n
  CROSS JOIN (SELECT max(step) AS step, coalesce(sum(rank) FILTER (vid NOT IN (SELECT src FROM e)), 0) AS loose FROM t HAVING max(step) < 6) s
  LEFT JOIN (SELECT e.dst AS vid, sum(rank / deg) AS m FROM t JOIN e ON e.src = t.vid GROUP BY e.dst) g ON g.vid = v.vid)
 SELECT vid, round(rank, 6) AS rank FROM t WHERE step = 6""")


def w_pagerank_tol(spark, d):
    """Stops when a step moves less than 1e-6 in all; ranks to 5 places."""
    got = vertex.pagerank(graph(spark, d, "trade"), 60, tol=1e-6).vertices
    return got.select("vid", F.round("value", 5).alias("rank"))


_add("w_pagerank_tol", w_pagerank_tol)
_add("w_sssp_cust", _dists("cust"), SSSP_CUST)
_add("w_sssp_cust_weighted", _dists("cust", True), dist_sql(edge_sql("cust"), TOP, "weight"))


def w_sssp_session(spark, d):
    """From the first event of the user with most events: one live vertex a superstep."""
    g = graph(spark, d, "session")
    first = table(spark, d, "events").groupBy("user_id").agg(F.count("*").alias("n"), F.min(F.struct("ts", "event_id")).alias("first")).orderBy(F.desc("n"), "user_id").first()
    got = vertex.sssp(g, first["first"].event_id, True).vertices
    return got.where("value IS NOT NULL").select("vid", F.col("value").alias("dist"))


_add("w_sssp_session", w_sssp_session, f"""WITH e AS ({edge_sql('session')}), u AS (SELECT user_id FROM events GROUP BY 1 ORDER BY count(*) DESC, user_id LIMIT 1),
 c AS (SELECT event_id, lag(event_id) OVER (ORDER BY ts, event_id) AS prev FROM events WHERE user_id IN (SELECT user_id FROM u))
 SELECT event_id AS vid, sum(coalesce(weight, 0)) OVER (ORDER BY (SELECT (ts, event_id) FROM events x WHERE x.event_id = c.event_id))::BIGINT AS dist FROM c LEFT JOIN e ON e.src = c.prev""")
for _g in ("order", "cust", "copy"):
    _add(f"w_cc_{_g}", _labels(_g), label_sql(PAIR_SQL[_g]))


def w_cc_web(spark, d):
    """Messages to link targets that no vertex stands for create them."""
    e = graph(spark, d, "web").edges
    both = e.union(e.select("dst", "src", "weight")).toDF("src", "dst", "weight").distinct()
    g = Graph.of(both, vertices=table(spark, d, "pages").select(F.col("page_id").alias("vid")), complete=False)
    got = vertex.connected_components(g, HASH, creates=True).vertices
    return got.where("degree > 0").select("vid", F.col("value").alias("label"))


def w_missing_vertex_web(spark, d):
    """What one round of messages along links makes of pages and missing targets: (vid, received, created)."""
    pages = table(spark, d, "pages").select(F.col("page_id").alias("vid"))
    g = Graph.of(graph(spark, d, "web").edges, vertices=pages, complete=False)

    def compute(c):
        return Step(F.coalesce(c.payload, F.lit(0)) if c.superstep == 2 else F.lit(None), F.lit(True), F.lit(1).cast("long") if c.superstep == 1 else None)

    program = Program("touch", "long", "long", COUNT, lambda: F.lit(None), compute, creates=True)
    got = run(g, program, LEFT, 2).vertices.where("value IS NOT NULL")
    return got.join(pages.withColumn("old", F.lit(True)), "vid", "left").select("vid", F.col("value").alias("received"), F.col("old").isNull().alias("created"))


_add("w_missing_vertex_web", w_missing_vertex_web, f"SELECT dst AS vid, count(*)::BIGINT AS received, dst NOT IN (SELECT page_id FROM pages) AS created FROM ({edge_sql('web')}) GROUP BY 1")


def w_cc_web_all(spark, d):
    return vertex.connected_components(Graph.of(graph(spark, d, "web").edges, symmetric=True), HASH).vertices.select("vid", F.col("value").alias("label"))


_add("w_cc_web", w_cc_web_all, label_sql(edge_sql("web")))
_add("w_cc_sizes", lambda s, d: _labels("order")(s, d).groupBy("label").agg(F.count("*").alias("n")), label_sql(PAIR_SQL["order"], "SELECT label, count(*)::BIGINT AS n FROM t GROUP BY 1"))
_add("w_cc_pointer_jump", lambda s, d: structure.min_label(PAIRS["order"](s, d), graph(s, d, "order").vertices), label_sql(PAIR_SQL["order"]))

_add("w_cc_hash_to_min", lambda s, d: structure.hash_to_min(PAIRS["order"](s, d), graph(s, d, "order").vertices), label_sql(PAIR_SQL["order"]))


def w_sssp_parents(spark, d):
    g = graph(spark, d, "cust")
    return vertex.sssp_parents(g, vertex.highest_degree(g), weighted=True)


_add("w_sssp_parents", w_sssp_parents, dist_sql(edge_sql("cust"), TOP, "weight", """SELECT t.vid, t.dist, CASE WHEN t.dist = 0 THEN t.vid ELSE min(e.src) END AS parent
 FROM t LEFT JOIN (SELECT e.src, e.dst, u.dist + weight AS dist FROM e JOIN t u ON u.vid = e.src) e ON e.dst = t.vid AND e.dist = t.dist GROUP BY t.vid, t.dist"""))


def w_cc_scaled(spark, d):
    g = structure.scale_up(graph(spark, d, "order"), 4)
    got = vertex.connected_components(g, vertex.COMPONENT_PLAN).vertices
    return got.groupBy(F.col("value").alias("label")).agg(F.count("*").alias("size"))


_add("w_cc_scaled", w_cc_scaled, label_sql(PAIR_SQL["order"], "SELECT label + k * (SELECT max(vid) + 1 FROM t) AS label, count(*)::BIGINT AS size FROM t, (SELECT unnest(range(0, 4)) AS k) GROUP BY 1"))


def w_reach_cycle(spark, d):
    g = graph(spark, d, "cycle_sparse")
    return vertex.reachability(g, [vertex.highest_degree(g)])


_add("w_reach_cycle", w_reach_cycle, dist_sql(edge_sql("cycle_sparse"), TOP, rest="SELECT vid, dist AS hops FROM t"))


def w_reach_targets(spark, d):
    """Whether the vertices with the highest in-degree are reached; the run ends once they are."""
    g = graph(spark, d, "cycle_sparse")
    targets = [r.dst for r in g.edges.groupBy("dst").count().orderBy(F.desc("count"), "dst").limit(3).collect()]
    return vertex.reachability(g, [vertex.highest_degree(g)], targets).where(F.col("vid").isin(targets))


_add("w_reach_targets", w_reach_targets, dist_sql(edge_sql("cycle_sparse"), TOP, rest="SELECT vid, dist AS hops FROM t WHERE vid IN (SELECT dst FROM e GROUP BY dst ORDER BY count(*) DESC, dst LIMIT 3)"))


# ---------------------------------------------------------------- triangles, cliques, samples, statistics

_TRI = "WITH e AS MATERIALIZED ({p}), t AS (SELECT a.src AS x, a.dst AS y, b.dst AS z FROM e a JOIN e b ON a.dst = b.src JOIN e c ON c.src = a.src AND c.dst = b.dst) "
for _g in ("copy", "knn"):
    _add(f"w_triangles_{_g}", lambda s, d, g=_g: structure.triangle_count(PAIRS[g](s, d)), _TRI.format(p=PAIR_SQL[_g]) + "SELECT vid, count(*)::BIGINT AS n FROM (SELECT unnest([x, y, z]) AS vid FROM t) GROUP BY 1")
_add("w_triangles_total", lambda s, d: structure.triangles(PAIRS["copy"](s, d)).agg(F.count("*").alias("n")), _TRI.format(p=PAIR_SQL["copy"]) + "SELECT count(*)::BIGINT AS n FROM t")
_add("w_cliques_knn", lambda s, d: structure.maximal_cliques(PAIRS["knn"](s, d)), f"""WITH p AS MATERIALIZED ({PAIR_SQL['knn']}), e AS MATERIALIZED (SELECT src, dst FROM p UNION SELECT dst, src FROM p),
 c2 AS (SELECT [src, dst] AS m FROM p), c3 AS (SELECT list_append(m, dst) AS m FROM c2 JOIN p ON p.src = m[2] WHERE EXISTS (FROM e WHERE e.src = m[1] AND e.dst = p.dst)),
 c4 AS (SELECT list_append(m, dst) AS m FROM c3 JOIN p ON p.src = m[3] WHERE EXISTS (FROM e WHERE e.src = m[1] AND e.dst = p.dst) AND EXISTS (FROM e WHERE e.src = m[2] AND e.dst = p.dst)),
 c5 AS (SELECT list_append(m, dst) AS m FROM c4 JOIN p ON p.src = m[4] WHERE (SELECT count(*) FROM e WHERE e.src IN (m[1], m[2], m[3]) AND e.dst = p.dst) = 3),
 a AS (SELECT m FROM c2 UNION ALL SELECT m FROM c3 UNION ALL SELECT m FROM c4 UNION ALL SELECT m FROM c5), r AS (SELECT row_number() OVER () AS id, m FROM a),
 u AS (SELECT id, len(m) AS size, unnest(m) AS v FROM r), x AS (SELECT DISTINCT id FROM (SELECT u.id, e.dst, count(*) AS k, any_value(size) AS size FROM u JOIN e ON e.src = u.v GROUP BY 1, 2) WHERE k = size)
 SELECT len(m)::BIGINT AS size, array_to_string(m, ',') AS members FROM r WHERE id NOT IN (SELECT id FROM x)""")
_add("w_recommend_copy", lambda s, d: structure.recommend(PAIRS["copy"](s, d), 3), f"""WITH p AS MATERIALIZED ({PAIR_SQL['copy']}), e AS MATERIALIZED (SELECT src, dst FROM p UNION SELECT dst, src FROM p),
 c AS (SELECT a.src AS vid, b.dst AS candidate, count(*)::BIGINT AS common FROM e a JOIN e b ON a.dst = b.src WHERE a.src <> b.dst GROUP BY 1, 2),
 k AS (SELECT c.* FROM c ANTI JOIN e ON e.src = c.vid AND e.dst = c.candidate), r AS (SELECT *, row_number() OVER (PARTITION BY vid ORDER BY common DESC, candidate)::BIGINT AS rn FROM k)
 SELECT vid, candidate, common, rn FROM r WHERE rn <= 3""")


def w_sample_walk(spark, d):
    g = graph(spark, d, "user")
    return structure.random_walk_sample(g.edges, g.vertices, 8, 12)


_add("w_sample_walk", w_sample_walk, f"""WITH RECURSIVE e AS MATERIALIZED (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS i, count(*) OVER (PARTITION BY src) AS n FROM ({edge_sql('user')})),
 s AS (SELECT vid FROM (SELECT src AS vid FROM e UNION SELECT dst FROM e) ORDER BY md5('1:' || vid::VARCHAR), vid LIMIT 8),
 t(step, home, here) AS (SELECT 0, vid, vid FROM s UNION ALL
  SELECT step + 1, home, CASE WHEN x.n IS NULL OR draw % 7 = 0 THEN home ELSE (SELECT dst FROM e WHERE e.src = here AND e.i = (draw // 7) % x.n) END
  FROM (SELECT t.*, ('0x' || substr(md5('1:' || step || ':' || home::VARCHAR), 1, 12))::BIGINT AS draw, (SELECT any_value(n) FROM e WHERE e.src = here) AS n FROM t WHERE step < 12) x)
 SELECT DISTINCT src, dst FROM e WHERE src IN (SELECT here FROM t) AND dst IN (SELECT here FROM t)""")


def w_graph_stats(spark, d):
    out = None
    for name in ("trade", "cust", "order", "cycle", "session", "user", "reply", "region", "webbip"):
        one = structure.graph_stats(graph(spark, d, name)).select(F.lit(name).alias("graph"), "*")
        out = one if out is None else out.unionByName(one)
    return out


_STAT = """SELECT '{g}' AS graph, count(*)::BIGINT AS vertices, sum(coalesce(d, 0))::BIGINT AS edges, round(sum(coalesce(d, 0)) / count(*), 6)::DOUBLE AS avg_degree, max(coalesce(d, 0))::BIGINT AS max_degree
 FROM (SELECT src AS vid FROM ({e}) UNION SELECT dst FROM ({e})) LEFT JOIN (SELECT src AS vid, count(*) AS d FROM ({e}) GROUP BY 1) USING (vid)"""
_add("w_graph_stats", w_graph_stats, " UNION ALL ".join(_STAT.format(g=g, e=edge_sql(g)) for g in ("trade", "cust", "order", "cycle", "session", "user", "reply", "region", "webbip")))
_add("w_scale_up", lambda s, d: structure.graph_stats(structure.scale_up(graph(s, d, "order"), 3)), f"""WITH e AS ({edge_sql('order')}), d AS (SELECT src, count(*) AS d FROM e GROUP BY 1)
 SELECT 3 * count(*)::BIGINT AS vertices, 3 * sum(d)::BIGINT AS edges, round(sum(d) / count(*), 6)::DOUBLE AS avg_degree, max(d)::BIGINT AS max_degree FROM d""")


# ---------------------------------------------------------------- trees, lists, other components

_REGION = edge_sql("region")
_BFS = """SELECT t.vid, CASE WHEN t.dist = 0 THEN t.vid ELSE min(e.src) END AS parent, t.dist AS depth FROM t LEFT JOIN (SELECT e.src, e.dst, u.dist FROM e JOIN t u ON u.vid = e.src) e ON e.dst = t.vid AND e.dist = t.dist - 1 GROUP BY t.vid, t.dist"""


def w_bfs_tree_region(spark, d):
    return vertex.bfs_tree(Graph.of(EDGES(spark, d, "region"), symmetric=True), 0)


def EDGES(spark, d, name: str) -> DataFrame:
    from .graphs import DIRECTED

    return DIRECTED[name](spark, d)


_add("w_bfs_tree_region", w_bfs_tree_region, dist_sql(f"SELECT src, dst FROM ({_REGION}) UNION SELECT dst, src FROM ({_REGION})", "SELECT 0 AS vid", rest=_BFS))


def w_bfs_tree_cust(spark, d):
    g = graph(spark, d, "cust")
    return vertex.bfs_tree(g, vertex.highest_degree(g))


_add("w_bfs_tree_cust", w_bfs_tree_cust, dist_sql(edge_sql("cust"), TOP, rest=_BFS))


def _region_tree(spark, d) -> DataFrame:
    return EDGES(spark, d, "region").select(F.col("src").alias("parent"), F.col("dst").alias("child"))


_add("w_euler_region", lambda s, d: structure.euler_tour(_region_tree(s, d)), f"""WITH a AS MATERIALIZED (SELECT src, dst FROM ({_REGION}) UNION SELECT dst, src FROM ({_REGION})),
 r AS (SELECT src, dst, coalesce(lead(dst) OVER w, first_value(dst) OVER w) AS nxt FROM a WINDOW w AS (PARTITION BY src ORDER BY dst))
 SELECT a.src, a.dst, r.src AS next_src, r.nxt AS next_dst FROM a JOIN r ON r.src = a.dst AND r.dst = a.src""")


def _listrank(name: str):
    def f(spark, d):
        e = EDGES(spark, d, name)
        ends = e.select(F.col("src").alias("vid")).union(e.select("dst")).distinct()
        return structure.list_rank(ends.join(e.select(F.col("src").alias("vid"), F.col("dst").alias("next")), "vid", "left"))

    return f


_add("w_listrank_session", _listrank("session"), "SELECT event_id AS vid, (row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) - 1)::BIGINT AS rank FROM events WHERE user_id IN (SELECT user_id FROM events GROUP BY 1 HAVING count(*) > 1)")
_add("w_listrank_reply", _listrank("reply"), "SELECT 16 * conv_id + turn AS vid, (row_number() OVER (PARTITION BY conv_id ORDER BY turn DESC) - 1)::BIGINT AS rank FROM conversations WHERE conv_id IN (SELECT conv_id FROM conversations GROUP BY 1 HAVING count(*) > 1)")
_add("w_listrank_walk", lambda s, d: vertex.list_rank_walk(Graph.of(EDGES(s, d, "reply"))), "SELECT 16 * conv_id + turn AS vid, (row_number() OVER (PARTITION BY conv_id ORDER BY turn DESC) - 1)::BIGINT AS rank FROM conversations WHERE conv_id IN (SELECT conv_id FROM conversations GROUP BY 1 HAVING count(*) > 1)")
_add("w_treeorder_region", lambda s, d: structure.tree_order(_region_tree(s, d), 0), f"""WITH RECURSIVE e AS MATERIALIZED ({_REGION}), t(vid, path, depth) AS (SELECT 0::BIGINT, lpad('0', 12, '0'), 0 UNION ALL
 SELECT e.dst, path || '/' || lpad(e.dst::VARCHAR, 12, '0'), depth + 1 FROM t JOIN e ON e.src = t.vid), s AS (SELECT a.vid, count(*)::BIGINT AS size FROM t a JOIN t b ON b.path = a.path OR starts_with(b.path, a.path || '/') GROUP BY 1),
 o AS (SELECT t.*, size, row_number() OVER (ORDER BY path)::BIGINT AS pre FROM t JOIN s USING (vid))
 SELECT vid, pre, (pre + size - 1 - depth)::BIGINT AS post, size, depth::BIGINT AS depth FROM o""")


def _reply_merge(spark, d):
    e = EDGES(spark, d, "reply")
    nodes = table(spark, d, "conversations").select((F.col("conv_id") * 16 + F.col("turn")).alias("vid"), F.col("text").alias("seq"))
    got = structure.merge_paths(nodes, e.select(F.col("src").alias("vid"), F.col("dst").alias("next")))
    return got.select("head", F.md5(F.col("seq").cast("binary")).alias("seq_md5"), "length")


def _session_merge(spark, d):
    e = EDGES(spark, d, "session")
    nodes = table(spark, d, "events").select(F.col("event_id").alias("vid"), F.col("event_type").alias("seq"))
    got = structure.merge_paths(nodes, e.select(F.col("src").alias("vid"), F.col("dst").alias("next")))
    return got.select("head", F.md5(F.col("seq").cast("binary")).alias("seq_md5"), "length")


_add("w_merge_reply", _reply_merge, "SELECT min(16 * conv_id + turn) AS head, md5(string_agg(text, ' ' ORDER BY turn)) AS seq_md5, count(*)::BIGINT AS length FROM conversations GROUP BY conv_id")
_add("w_merge_session", _session_merge, "SELECT arg_min(event_id, (ts, event_id)) AS head, md5(string_agg(event_type, ' ' ORDER BY ts, event_id)) AS seq_md5, count(*)::BIGINT AS length FROM events GROUP BY user_id")
_add("w_bicc_cust", lambda s, d: structure.biconnected(PAIRS["cust"](s, d))["edges"])
_add("w_articulation", lambda s, d: structure.biconnected(PAIRS["cust"](s, d))["articulation"])
_add("w_bridges", lambda s, d: structure.biconnected(PAIRS["cust"](s, d))["bridges"])
_add("w_scc_cycle_sparse", lambda s, d: structure.scc(graph(s, d, "cycle_sparse")))
_add("w_scc_user", lambda s, d: structure.scc(graph(s, d, "user")), f"""WITH RECURSIVE e AS MATERIALIZED (SELECT DISTINCT src, dst FROM ({edge_sql('user')})), v AS (SELECT src AS vid FROM e UNION SELECT dst FROM e),
 r(a, b) AS (SELECT vid, vid FROM v UNION SELECT r.a, e.dst FROM r JOIN e ON e.src = r.b)
 SELECT x.a AS vid, max(x.b) AS label FROM r x JOIN r y ON x.a = y.b AND x.b = y.a GROUP BY 1""")
_add("w_closure_region", lambda s, d: structure.transitive_closure(EDGES(s, d, "region")), f"""WITH RECURSIVE e AS MATERIALIZED ({_REGION}), t(src, dst, hops) AS (SELECT src, dst, 1::BIGINT FROM e UNION ALL SELECT t.src, e.dst, hops + 1 FROM t JOIN e ON e.src = t.dst)
 SELECT src, dst, hops FROM t""")
_add("w_closure_reply", lambda s, d: structure.transitive_closure(EDGES(s, d, "reply"), semi_naive=False), f"""WITH RECURSIVE e AS MATERIALIZED ({edge_sql('reply')}), t(src, dst, hops) AS (SELECT src, dst, 1::BIGINT FROM e UNION ALL SELECT t.src, e.dst, hops + 1 FROM t JOIN e ON e.src = t.dst)
 SELECT src, dst, hops FROM t""")


# ---------------------------------------------------------------- assembly

_READS = """SELECT DISTINCT regexp_replace(lower(line), '[^a-z]', '', 'g') AS read FROM (SELECT unnest(string_split(text, chr(10))) AS line FROM documents WHERE lang = 'en')"""
_KMERS = f"SELECT substr(read, i, 12) AS kmer FROM (SELECT read, unnest(range(1, length(read) - 10)) AS i FROM ({_READS}) WHERE length(read) >= 12)"


def _graph_of_reads(spark, d):
    nodes, edges = assembly.debruijn(assembly.reads(spark, d))
    return structure.cut(nodes), structure.cut(edges)


_add("w_debruijn", lambda s, d: _graph_of_reads(s, d)[0], f"SELECT kmer, count(*)::BIGINT AS coverage FROM ({_KMERS}) GROUP BY 1")
_add("w_clean_lowcov", lambda s, d: assembly.drop_low_coverage(*_graph_of_reads(s, d))[0], f"SELECT kmer, count(*)::BIGINT AS coverage FROM ({_KMERS}) GROUP BY 1 HAVING count(*) >= 2")


def _units(pattern=None):
    def f(spark, d):
        read = assembly.reads(spark, d)
        kept = assembly.clean_reads(read, pattern) if pattern else assembly.read_units(read, with_links=False)[0]
        return kept.select(F.substring("seq", 1, 12).alias("head"), F.md5(F.col("seq").cast("binary")).alias("seq_md5"), F.col("coverage").cast("long").alias("coverage"), F.col("n").cast("long").alias("n"))

    return f


_add("w_merge_debruijn", _units())
_add("w_clean_tips", _units("tips"))
_add("w_clean_bubbles", _units("bubbles"))
_add("w_clean_bridges", _units("bridges"))
_add("w_clean_small", lambda s, d: compact.big_components(assembly.reads(s, d), 12, 20))
_add("w_clean_chain", lambda s, d: assembly.clean_chain(assembly.reads(s, d)))


# ---------------------------------------------------------------- plans, statistics, state

for _j in (Join.FULL, Join.LEFT):
    _add(f"w_join_equiv_pr_{_j.value}", _ranks("trade", 5, PlanHints(_j, GroupBy.HASH)), rank_sql(edge_sql("trade"), 5))
    _add(f"w_join_equiv_sssp_{_j.value}", _dists("cust", False, PlanHints(_j, GroupBy.HASH)), SSSP_CUST)
    _add(f"w_join_equiv_cc_{_j.value}", _labels("order", PlanHints(_j, GroupBy.HASH)), label_sql(PAIR_SQL["order"]))
for _i, (_gb, _cn) in enumerate(((GroupBy.SORT, Connector.PLAIN), (GroupBy.HASH, Connector.PLAIN), (GroupBy.SORT, Connector.MERGE), (GroupBy.HASH, Connector.MERGE))):
    _add(f"w_groupby_c{_i + 1}", _ranks("trade", 10, PlanHints(Join.FULL, _gb, _cn)), rank_sql(edge_sql("trade")))
for _s in Store:
    _add(f"w_store_{_s.value}", _dists("cust", True, PlanHints(Join.LEFT, GroupBy.HASH, store=_s)), dist_sql(edge_sql("cust"), TOP, "weight"))


def _plan16(algo: str, at_once: int = 4):
    """A method on the order graph under all 16 plans, each to its end: how many plans give each row.

    Supersteps of small graphs leave most cores idle, so ``at_once`` plans run side by side, each in a session of its
    own, since a plan's settings are its session's; their tables have few partitions while the graph has few rows.
    """
    name = {"pagerank": "rank", "sssp": "dist", "cc": "label"}[algo]

    def f(spark, d):
        root = f"{shared_folder(spark)}/plan16-{uuid.uuid4().hex}"
        graph(spark, d, "order").edges.write.parquet(f"{root}/edges")
        Graph.of(spark.read.parquet(f"{root}/edges")).vertices.write.parquet(f"{root}/vertices")
        kept = Graph(spark.read.parquet(f"{root}/vertices"), spark.read.parquet(f"{root}/edges"))
        source = vertex.highest_degree(kept) if algo == "sssp" else None
        parts = row_partitions(spark, max(kept.vertices.count(), kept.edges.count()))

        def one(n: int, hints: PlanHints) -> None:
            own = fresh_session(spark)
            g = Graph(own.read.parquet(f"{root}/vertices"), own.read.parquet(f"{root}/edges"))
            if algo == "pagerank":
                got = vertex.pagerank(g, 5, fixed_point=True, hints=hints).vertices
            else:
                got = (vertex.sssp(g, source, hints=hints) if algo == "sssp" else vertex.connected_components(g, hints)).vertices
            got.where("value IS NOT NULL").select("vid", F.col("value").alias(name)).write.parquet(f"{root}/out/plan={n}")

        with ThreadPoolExecutor(at_once) as pool:
            for done in [pool.submit(one, n, replace(hints, partitions=parts)) for n, hints in enumerate(all_plans())]:
                done.result()
        return spark.read.schema(f"vid long, {name} long").parquet(*(f"{root}/out/plan={n}" for n in range(len(all_plans())))).groupBy("vid", name).agg(F.count("*").alias("plans"))

    return f


_add("w_plan16_pagerank", _plan16("pagerank"), f"SELECT *, 16::BIGINT AS plans FROM ({rank_sql(edge_sql('order'), 5)})")
_add("w_plan16_sssp", _plan16("sssp"), dist_sql(edge_sql("order"), TOP, rest="SELECT vid, dist, 16::BIGINT AS plans FROM t"))
_add("w_plan16_cc", _plan16("cc"), label_sql(PAIR_SQL["order"], "SELECT vid, label, 16::BIGINT AS plans FROM t"))


def _superstep_stats(algo: str):
    def f(spark, d):
        g = graph(spark, d, "cust")
        result = vertex.sssp(g, vertex.highest_degree(g), hints=LEFT) if algo == "sssp" else vertex.connected_components(g, HASH)
        return result.stats_frame(spark).select("superstep", "vertices", "senders", "messages")

    return f


_add("w_superstep_stats_sssp", _superstep_stats("sssp"), dist_sql(edge_sql("cust"), TOP, rest="""SELECT coalesce(l.dist, m.m)::BIGINT + 1 AS superstep, (SELECT count(DISTINCT src) FROM e)::BIGINT AS vertices, coalesce(l.n, 0)::BIGINT AS senders, coalesce(l.k, 0)::BIGINT AS messages
 FROM (SELECT dist, count(*) AS n, sum((SELECT count(*) FROM e WHERE e.src = t.vid)) AS k FROM t GROUP BY 1) l FULL JOIN (SELECT max(dist) + 1 AS m FROM t) m ON l.dist = m.m"""))
_add("w_superstep_stats_cc", _superstep_stats("cc"), f"""WITH RECURSIVE e AS MATERIALIZED ({edge_sql('cust')}), deg AS MATERIALIZED (SELECT src AS vid, count(*) AS deg FROM e GROUP BY 1),
 t(step, vid, label, changed) AS (SELECT 1, vid, vid, true FROM deg UNION ALL
  SELECT step + 1, vid, least(label, m), coalesce(m < label, false) FROM (SELECT t.step, t.vid, t.label, min(u.label) AS m FROM t JOIN e ON e.dst = t.vid LEFT JOIN t u ON u.vid = e.src AND u.changed GROUP BY 1, 2, 3)
  WHERE (SELECT bool_or(changed) FROM t))
 SELECT step::BIGINT AS superstep, count(*)::BIGINT AS vertices, count(*) FILTER (changed)::BIGINT AS senders, coalesce(sum(deg) FILTER (changed), 0)::BIGINT AS messages FROM t JOIN deg USING (vid) GROUP BY 1""")


def w_gs_aggregates(spark, d):
    g = vertex.degree_aggregates(graph(spark, d, "cust"))
    rows = [("avg", round(g["total"] / g["n"], 6)), ("max", float(g["high"])), ("min", float(g["low"])), ("sum", float(g["total"]))]
    return spark.createDataFrame(rows, "name string, value double")


_add("w_gs_aggregates", w_gs_aggregates, f"""WITH d AS (SELECT count(*) AS d FROM ({edge_sql('cust')}) GROUP BY src) SELECT 'min' AS name, min(d)::DOUBLE AS value FROM d UNION ALL SELECT 'max', max(d) FROM d
 UNION ALL SELECT 'sum', sum(d) FROM d UNION ALL SELECT 'avg', round(avg(d), 6) FROM d""")
for _name, _c, _e in (("min", MIN, "min(src)"), ("max", MAX, "max(src)"), ("sum", SUM, "sum(src)::BIGINT")):
    _add(f"w_combine_{_name}", lambda s, d, c=_c: vertex.message_fold(graph(s, d, "cust"), c), f"SELECT dst AS vid, {_e} AS payload FROM ({edge_sql('cust')}) GROUP BY 1")
_add("w_combine_count", lambda s, d: vertex.message_fold(graph(s, d, "cust"), COUNT, F.lit(1).cast("long")), f"SELECT dst AS vid, count(*)::BIGINT AS payload FROM ({edge_sql('cust')}) GROUP BY 1")


def w_combine_list(spark, d):
    raw = graph(spark, d, "cust").edges.select(F.col("dst").alias("vid"), F.col("src").alias("payload"))
    from .plans.combine import combine

    got = combine(raw, LIST, GroupBy.HASH, Connector.PLAIN, 8)
    return got.select("vid", F.array_join(F.transform("payload", lambda v: v.cast("string")), ",").alias("payload"))


_add("w_combine_list", w_combine_list, f"SELECT dst AS vid, string_agg(src::VARCHAR, ',' ORDER BY src) AS payload FROM ({edge_sql('cust')}) GROUP BY 1")


def w_combine_struct_min(spark, d):
    from .plans.combine import STRUCT_MIN, combine

    raw = graph(spark, d, "cust").edges.select(F.col("dst").alias("vid"), F.struct("weight", "src").alias("payload"))
    got = combine(raw, STRUCT_MIN, GroupBy.SORT, Connector.PLAIN, 8)
    return got.select("vid", "payload.weight", "payload.src")


_add("w_combine_struct_min", w_combine_struct_min, f"SELECT dst AS vid, weight, min(src) AS src FROM (SELECT *, min(weight) OVER (PARTITION BY dst) AS low FROM ({edge_sql('cust')})) WHERE weight = low GROUP BY 1, 2")


def _mutated(kind: str):
    """Suppliers as vertices; mutations of them resolved: inserts, deletes, or both on one vertex."""

    def f(spark, d):
        s = table(spark, d, "supplier").select(F.col("s_suppkey").alias("vid"), F.lit(True).alias("halt"), F.col("s_nationkey").cast("long").alias("value"))
        new = lambda shift: F.struct((F.col("value") + shift).alias("value"))
        insert = s.select((F.col("vid") + (100_000 if kind == "insert" else 0)).alias("vid"), F.lit("I").alias("op"), new(1).alias("vertex"))
        second = s.select((F.col("vid") + (100_000 if kind == "insert" else 0)).alias("vid"), F.lit("I").alias("op"), new(2).alias("vertex"))
        delete = s.where("value < 10").select("vid", F.lit("D").alias("op"), F.lit(None).cast("struct<value:long>").alias("vertex"))
        muts = {"insert": insert.union(second), "delete": delete.union(delete), "conflict": delete.union(second.where("vid % 2 = 0")).union(insert.where("vid % 2 = 0"))}[kind]
        return apply_mutations(s, muts).select("vid", "halt", "value")

    return f


_S = "SELECT s_suppkey AS vid, true AS halt, s_nationkey::BIGINT AS value FROM supplier"
_add("w_mutation_insert", _mutated("insert"), f"{_S} UNION ALL SELECT s_suppkey + 100000, false, s_nationkey + 1 FROM supplier")
_add("w_mutation_delete", _mutated("delete"), f"{_S} WHERE s_nationkey >= 10")
_add("w_mutation_conflict", _mutated("conflict"), "SELECT s_suppkey AS vid, s_suppkey % 2 <> 0 AS halt, (CASE WHEN s_suppkey % 2 = 0 THEN s_nationkey + 1 ELSE s_nationkey END)::BIGINT AS value FROM supplier WHERE s_suppkey % 2 = 0 OR s_nationkey >= 10")


def w_row_program(spark, d):
    """A row program in Python: each vertex of the copy graph keeps the sum of its neighbours' ids and drops edges to larger ones."""
    g = graph(spark, d, "copy")

    def compute(v, msgs, gs, out):
        if gs["superstep"] == 1:
            for dst, _ in v.edges:
                out.send(dst, v.vid)
        else:
            v.value = sum(msgs)
            v.edges = [e for e in v.edges if e[0] < v.vid]
            out.halt()

    got = run_rows(g, RowProgram("sums", "long", "long", compute), 2)
    return got.select("vid", "value", F.size("edges").cast("long").alias("kept"))


_add("w_row_program", w_row_program, f"SELECT src AS vid, sum(dst)::BIGINT AS value, count(*) FILTER (dst < src)::BIGINT AS kept FROM ({edge_sql('copy')}) GROUP BY 1")


def _mutating(kind: str):
    """Suppliers as vertices that ask for mutations in their first superstep: insertions of others, their own deletion, or
    both on one vertex; what is resolved shows in the second."""

    def compute(v, msgs, gs, out):
        if gs["superstep"] == 1:
            v.value = v.edges[0][1]
            if kind == "insert":
                out.add_vertex(v.vid + 100_000, v.value + 2)
                out.add_vertex(v.vid + 100_000, v.value + 1)
            elif v.value < 10:
                out.remove_vertex(v.vid)
            if kind == "conflict" and v.vid % 2 == 0:
                out.add_vertex(v.vid, v.value + 2)
                out.add_vertex(v.vid, v.value + 1)
        out.halt()

    def f(spark, d):
        edges = table(spark, d, "supplier").selectExpr("s_suppkey AS src", "s_nationkey + 1000000L AS dst", "cast(s_nationkey AS long) AS weight")
        got = run_rows(Graph.of(edges, complete=False), RowProgram("mutate", "long", "long", compute))
        return got.select("vid", "value")

    return f


_N = "SELECT s_suppkey AS vid, s_nationkey::BIGINT AS value FROM supplier"
_add("w_mutation_superstep_insert", _mutating("insert"), f"{_N} UNION ALL SELECT s_suppkey + 100000, s_nationkey + 1 FROM supplier")
_add("w_mutation_superstep_delete", _mutating("delete"), f"{_N} WHERE s_nationkey >= 10")
_add("w_mutation_superstep_conflict", _mutating("conflict"), "SELECT s_suppkey AS vid, (CASE WHEN s_suppkey % 2 = 0 THEN s_nationkey + 1 ELSE s_nationkey END)::BIGINT AS value FROM supplier WHERE s_suppkey % 2 = 0 OR s_nationkey >= 10")


def _mutating_columns(kind: str, join: Join):
    """The same mutations from a column program, under either join."""

    def compute(c):
        if c.superstep > 1:
            return Step(c.value, F.lit(True))
        away = F.when(c.value < 10, F.array(deletion(c.vid, "long"))).otherwise(F.array().cast("array<struct<vid:long,op:string,vertex:struct<value:long>>>"))
        made = [F.array(*[insertion(c.vid + shift, c.value + k) for k in (2, 1)]) for shift in (0, 100_000)]
        asks = {"insert": made[1], "delete": away, "conflict": F.concat(away, F.when(c.vid % 2 == 0, made[0]).otherwise(F.slice(made[0], 1, 0)))}
        return Step(c.value, F.lit(True), mutate=asks[kind])

    def f(spark, d):
        vertices = table(spark, d, "supplier").selectExpr("s_suppkey AS vid", "cast(s_nationkey AS long) AS nation")
        edges = vertices.selectExpr("vid AS src", "vid AS dst", "1L AS weight")
        program = Program("mutate_columns", "long", "long", COUNT, lambda: F.col("nation"), compute)
        return run(Graph(vertices, edges), program, PlanHints(join, GroupBy.HASH, store=Store.DELTA_LOG)).vertices.select("vid", "value")

    return f


for _kind in ("insert", "delete", "conflict"):
    for _j in (Join.FULL, Join.LEFT):
        _add(f"w_mutation_columns_{_kind}_{_j.value}", _mutating_columns(_kind, _j), SQL[f"w_mutation_superstep_{_kind}"])


def _posting(creates: bool, hints: PlanHints):
    """Customers and parts write to the vertex of half their id, to which no edge need lead: (vid, received)."""

    def compute(c):
        if c.superstep == 1:
            return Step(F.lit(None), F.lit(True), post=F.array(letter(F.floor(c.vid / 2), F.lit(1).cast("long"))))
        return Step(c.payload, F.lit(True))

    def f(spark, d):
        program = Program("post", "long", "long", SUM, lambda: F.lit(None), compute, creates=creates)
        got = run(graph(spark, d, "cust"), program, hints).vertices
        return got.where("value IS NOT NULL").select("vid", F.col("value").alias("received"))

    return f


_POSTED = f"WITH v AS (SELECT DISTINCT src AS vid FROM ({edge_sql('cust')})) SELECT vid // 2 AS vid, count(*)::BIGINT AS received FROM v GROUP BY 1"
_add("w_send_any_vertex", _posting(False, LEFT), f"SELECT * FROM ({_POSTED}) WHERE vid IN (SELECT src FROM ({edge_sql('cust')}))")
_add("w_send_any_vertex_creates", _posting(True, HASH), _POSTED)


def _chained(pipelined: bool):
    def f(spark, d):
        g = graph(spark, d, "order")
        job = Job(vertex.components_program(), vertex.COMPONENT_PLAN)
        return pipeline(g, [job, job], pipelined).vertices.select("vid", F.col("value").alias("label"))

    return f


_add("w_pipeline", _chained(True), label_sql(PAIR_SQL["order"]))
_add("w_pipeline_files", _chained(False), label_sql(PAIR_SQL["order"]))


def w_recover_cc(spark, d):
    """Stopped after superstep 4, resumed from the checkpoint taken at superstep 3."""
    path = f"{shared_folder(spark)}/recover-{uuid.uuid4().hex}"
    got = run_recoverable(graph(spark, d, "order"), vertex.components_program(), path, HASH, every=3, stop_after=4)
    return got.vertices.select("vid", F.col("value").alias("label"))


_add("w_recover_cc", w_recover_cc, label_sql(PAIR_SQL["order"]))


def w_checkpoint_manifest(spark, d):
    path = f"{shared_folder(spark)}/manifest-{uuid.uuid4().hex}"
    keeper = Checkpointer(spark, path)
    run(graph(spark, d, "order"), vertex.components_program(), HASH, max_supersteps=5, checkpoint=keeper, checkpoint_when=2)
    return spark.createDataFrame([(s,) for s in keeper.complete()], "superstep long")


_add("w_checkpoint_manifest", w_checkpoint_manifest, "SELECT unnest([3, 5])::BIGINT AS superstep")


# ---------------------------------------------------------------- baselines


def _baseline(system: str, algo: str):
    def f(spark, d):
        g = graph(spark, d, {"pagerank": "trade", "sssp": "cust", "cc": "order"}[algo])
        t = task(g, algo, vertex.highest_degree(g) if algo == "sssp" else None, steps=10)
        got = SYSTEMS[system](g, t)
        name = {"pagerank": "rank", "sssp": "dist", "cc": "label"}[algo]
        return got.where("value IS NOT NULL").select("vid", F.col("value").alias(name))

    return f


for _system in SYSTEMS:
    _add(f"b_{_system}_pagerank", _baseline(_system, "pagerank"), rank_sql(edge_sql("trade")))
    _add(f"b_{_system}_sssp", _baseline(_system, "sssp"), SSSP_CUST)
    _add(f"b_{_system}_cc", _baseline(_system, "cc"), label_sql(PAIR_SQL["order"]))

QUERIES |= relational.QUERIES | streams.QUERIES
SQL |= relational.SQL | streams.SQL
