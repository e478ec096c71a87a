"""The superstep engine on hand-traced graphs: outer-join cases, halting, mutations, plans, recovery."""

import pytest
from pyspark.sql import functions as F

from bspflow.algos import structure, vertex
from bspflow.model import Graph
from bspflow.operators.rowprogram import RowProgram, run_rows
from bspflow.plans.combine import MIN, SUM, combine
from bspflow.plans.hints import Connector, GroupBy, Join, PlanHints, Store, all_plans
from bspflow.plans.logical import active_set, apply_mutations, create_missing, deliver_full, is_active, literal_full_outer
from bspflow.runtime.failure import FailurePolicy
from bspflow.runtime.pipeline import Admission, Job, pipeline, run_recoverable
from bspflow.runtime.session import settings, shared_folder


def edges(spark, rows):
    return spark.createDataFrame([(a, b, w) for a, b, w in rows], "src long, dst long, weight long")


@pytest.fixture(scope="module")
def diamond(spark):
    """1 - 2, 1 - 3, 2 - 4, 3 - 4 (dearer), and 8 - 9 apart."""
    return Graph.of(edges(spark, [(1, 2, 1), (1, 3, 1), (2, 4, 5), (3, 4, 2), (8, 9, 1)]), symmetric=True)


def got(df):
    return {r[0]: r[1] for r in df.collect()}


def test_outer_join_cases(spark):
    state = spark.createDataFrame([(1, False, 10, 1), (2, True, 20, 1), (3, True, 30, 1)], "vid long, halt boolean, value long, degree long")
    msg = spark.createDataFrame([(2, 7), (4, 8)], "vid long, payload long")
    both = deliver_full(state, msg).unionByName(create_missing(state, msg))
    active = {r.vid: (r.value, r.payload) for r in both.where(is_active()).collect()}
    assert active == {1: (10, None), 2: (20, 7), 4: (None, 8)}
    whole = literal_full_outer(state.drop("degree"), msg)
    assert whole.select("vid", "payload").exceptAll(both.select("vid", "payload")).count() == 0


def test_active_set_prefers_messages(spark):
    live = spark.createDataFrame([(1,), (2,)], "vid long")
    msg = spark.createDataFrame([(2, 7), (3, 8)], "vid long, payload long")
    assert got(active_set(live, msg)) == {1: None, 2: 7, 3: 8}


def test_shortest_paths_under_all_plans(spark, diamond):
    for hints in all_plans():
        result = vertex.sssp(diamond, 1, weighted=True, hints=hints)
        assert got(result.vertices.select("vid", "value")) == {1: 0, 2: 1, 3: 1, 4: 3, 8: None, 9: None}, hints


def test_components_and_statistics(spark, diamond):
    for hints in (PlanHints(Join.FULL), PlanHints(Join.AUTO, sparse_below=0.9), PlanHints(Join.LEFT, store=Store.DELTA_LOG)):
        result = vertex.connected_components(diamond, hints)
        assert got(result.vertices.select("vid", "value")) == {1: 1, 2: 1, 3: 1, 4: 1, 8: 8, 9: 8}
        assert result.stats[0]["messages"] == 10 and result.stats[-1]["messages"] == 0


def test_rank_keeps_its_mass_and_counts_alike(spark, diamond):
    exact = got(vertex.pagerank(diamond, 6, fixed_point=True).vertices.select("vid", "value"))
    real = got(vertex.pagerank(diamond, 6).vertices.select("vid", "value"))
    assert abs(sum(real.values()) - 1) < 1e-9
    assert all(abs(exact[v] / vertex.UNIT - real[v]) < 1e-9 for v in real)


def test_dangling_rank_is_spread(spark):
    g = Graph.of(edges(spark, [(1, 2, 1), (2, 3, 1)]))
    ranks = got(vertex.pagerank(g, 20, dangling="redistribute").vertices.select("vid", "value"))
    assert abs(sum(ranks.values()) - 1) < 1e-9 and ranks[3] > ranks[2] > ranks[1]


def test_empty_graph_halts(spark):
    g = Graph.of(edges(spark, []))
    assert vertex.connected_components(g).vertices.count() == 0


def test_mutations_delete_before_insert_and_resolve(spark):
    state = spark.createDataFrame([(1, True, 5), (2, True, 6), (3, True, 7)], "vid long, halt boolean, value long")
    rows = [(1, "D", None), (1, "I", (9,)), (2, "D", None), (2, "D", None), (4, "I", (8,)), (4, "I", (3,))]
    muts = spark.createDataFrame(rows, "vid long, op string, vertex struct<value:long>")
    assert {(r.vid, r.halt, r.value) for r in apply_mutations(state, muts).collect()} == {(1, False, 9), (3, True, 7), (4, False, 3)}


def test_row_program_adds_removes_and_messages_any_vertex(spark):
    g = Graph.of(edges(spark, [(1, 2, 1), (2, 3, 1)]))

    def compute(v, msgs, gs, out):
        if gs["superstep"] == 1:
            if v.vid == 1:
                out.remove_vertex(3)
                out.add_vertex(10, 100)
                out.send(77, 5)
        else:
            v.value = (v.value or 0) + sum(msgs)
        out.halt()

    rows = {r.vid: r.value for r in run_rows(g, RowProgram("edit", "long", "long", compute)).collect()}
    assert rows == {1: None, 2: None, 10: 100, 77: 5}


def test_combiners_agree_under_all_strategies(spark):
    raw = spark.range(1000).select((F.col("id") % 17).alias("vid"), F.col("id").alias("payload"))
    for combiner, fold in ((MIN, min), (SUM, sum)):
        want = {k: fold(i for i in range(1000) if i % 17 == k) for k in range(17)}
        for g in GroupBy:
            for c in Connector:
                assert got(combine(raw, combiner, g, c, 4)) == want


def test_vertices_stay_where_they_are(spark):
    with settings(spark, **{"spark.sql.adaptive.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1"}):
        shared_folder(spark)
        state = spark.range(100).select(F.col("id").alias("vid"), F.lit(False).alias("halt"), F.col("id").alias("value"), F.lit(1).alias("degree")).repartition(4, "vid").sortWithinPartitions("vid").checkpoint()
        msg = spark.range(50).select(F.col("id").alias("vid"), F.col("id").alias("x")).repartition(3).groupBy("vid").agg(F.max("x").alias("payload")).checkpoint()
        plan = deliver_full(state, msg)._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan


def test_recovery_resumes_from_the_newest_whole_checkpoint(spark, tmp_path):
    chain = Graph.of(edges(spark, [(i, i + 1, 1) for i in range(12)]), symmetric=True)
    seen = []
    result = run_recoverable(chain, vertex.components_program(), f"file://{tmp_path}", PlanHints(Join.FULL, GroupBy.HASH), every=3, stop_after=5, interrupt=seen.append)
    assert seen == [1, 2] and set(got(result.vertices.select("vid", "value")).values()) == {0}
    assert result.stats[0]["superstep"] == 4


def test_failures_that_are_worth_a_retry():
    policy = FailurePolicy(2)
    assert policy.recoverable(OSError("disk")) and policy.recoverable(RuntimeError("ExecutorLostFailure"))
    assert not policy.recoverable(ValueError("bad")) and not policy.recoverable(RuntimeError("PythonException: java.io.IOException"))
    calls = []
    with pytest.raises(OSError):
        policy.run(lambda: calls.append(1) or (_ for _ in ()).throw(OSError("x")))
    assert len(calls) == 3


def test_pipeline_needs_one_schema(spark, diamond):
    job = Job(vertex.components_program(), PlanHints(Join.FULL, GroupBy.HASH))
    both = [got(pipeline(diamond, [job, job], p).vertices.select("vid", "value")) for p in (True, False)]
    assert both[0] == both[1] == {1: 1, 2: 1, 3: 1, 4: 1, 8: 8, 9: 8}
    with pytest.raises(ValueError):
        pipeline(diamond, [job, Job(vertex.pagerank_program(6, 2))])


def test_admission_refuses_what_never_fits():
    door = Admission(1, 100)
    assert door.run(60, lambda: 7) == 7
    with pytest.raises(ValueError):
        door.run(101, lambda: 7)


def test_trees_orders_and_lists(spark):
    tree = spark.createDataFrame([(0, 5), (0, 2), (2, 9), (2, 1), (5, 7)], "parent long, child long")
    rows = {r.vid: (r.pre, r.post, r["size"], r.depth) for r in structure.tree_order(tree, 0).collect()}
    assert rows == {0: (1, 6, 6, 0), 2: (2, 3, 3, 1), 1: (3, 1, 1, 2), 9: (4, 2, 1, 2), 5: (5, 5, 2, 1), 7: (6, 4, 1, 2)}
    chain = spark.createDataFrame([(i, i + 1 if i < 6 else None) for i in range(7)], "vid long, next long")
    assert got(structure.list_rank(chain)) == {i: 6 - i for i in range(7)}


def test_blocks_of_a_bow_tie(spark):
    pairs = edges(spark, [(1, 2, 1), (2, 3, 1), (1, 3, 1), (3, 4, 1), (4, 5, 1), (3, 5, 1), (5, 6, 1)])
    found = structure.biconnected(pairs)
    blocks = {}
    for r in found["edges"].collect():
        blocks.setdefault(r.block, set()).add((r.src, r.dst))
    assert sorted(map(sorted, blocks.values())) == [[(1, 2), (1, 3), (2, 3)], [(3, 4), (3, 5), (4, 5)], [(5, 6)]]
    assert {r.vid for r in found["articulation"].collect()} == {3, 5}
    assert {(r.src, r.dst) for r in found["bridges"].collect()} == {(5, 6)}


def test_strong_components(spark):
    g = Graph.of(edges(spark, [(1, 2, 1), (2, 3, 1), (3, 1, 1), (3, 4, 1), (4, 5, 1), (5, 4, 1), (6, 1, 1)]))
    assert got(structure.scc(g)) == {1: 3, 2: 3, 3: 3, 4: 5, 5: 5, 6: 6}


def test_closure_of_a_long_conversation_is_whole(spark, tmp_path):
    from bspflow.workloads import QUERIES

    spark.createDataFrame([(1, n) for n in range(25)], "conv_id long, turn long").write.parquet(f"{tmp_path}/conversations.parquet")
    rows = {(r.src, r.dst): r.hops for r in QUERIES["w_closure_reply"](spark, str(tmp_path)).collect()}
    assert rows == {(16 + a, 16 + b): b - a for a in range(25) for b in range(a + 1, 25)}


def test_copies_of_any_number_are_one_component(spark, tmp_path):
    from bspflow.workloads import QUERIES

    line = lambda c: c * 45
    texts = [(n, line("a")) for n in range(10, 70)] + [(5, line("b")), (69, line("b")), (2, line("c")), (3, line("c")), (4, line("d"))]
    spark.createDataFrame(texts, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    assert got(QUERIES["w_cc_copy"](spark, str(tmp_path))) == {**{n: 5 for n in [5, *range(10, 70)]}, 2: 2, 3: 2}


def test_cliques_and_triangles(spark):
    pairs = edges(spark, [(a, b, 1) for a in range(5) for b in range(a + 1, 5)] + [(4, 9, 1)])
    assert {(r["size"], r.members) for r in structure.maximal_cliques(pairs).collect()} == {(5, "0,1,2,3,4"), (2, "4,9")}
    assert structure.triangles(pairs).count() == 10
