"""Plans that run side by side: settings stay in their session."""

from bspflow import workloads
from bspflow.algos import vertex
from bspflow.model import Graph
from bspflow.plans.hints import GroupBy, Join, PlanHints, Store
from bspflow.runtime.session import Pins, fresh_session, settings
from bspflow.workloads import QUERIES


def test_a_fresh_session_has_the_settings_and_keeps_its_own(spark):
    with settings(spark, **{"spark.sql.shuffle.partitions": "7"}):
        own = fresh_session(spark)
        assert own.conf.get("spark.sql.shuffle.partitions") == "7"
        own.conf.set("spark.sql.shuffle.partitions", "3")
        assert spark.conf.get("spark.sql.shuffle.partitions") == "7"


def test_all_plans_give_the_same_components(spark, tmp_path):
    rows = [(o, p, n, 50.0) for n, (o, p) in enumerate([(1, 1), (1, 2), (2, 2), (3, 9)], 1)]
    spark.createDataFrame(rows, "l_orderkey long, l_partkey long, l_linenumber int, l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = {(r.vid, r.label, r.plans) for r in QUERIES["w_plan16_cc"](spark, str(tmp_path)).collect()}
    assert got == {(v, 4, 16) for v in (4, 6, 8, 10)} | {(v, 12, 16) for v in (12, 38)}


def test_plans_of_a_small_graph_have_few_partitions(spark, tmp_path, monkeypatch):
    rows = [(n, n % 3, 1, 50.0) for n in range(9)]
    spark.createDataFrame(rows, "l_orderkey long, l_partkey long, l_linenumber int, l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    seen, run = [], vertex.connected_components
    monkeypatch.setattr(workloads.vertex, "connected_components", lambda g, hints: seen.append(hints.partitions) or run(g, hints))
    with settings(spark, **{"spark.sql.shuffle.partitions": "5"}):
        assert QUERIES["w_plan16_cc"](spark, str(tmp_path)).count() == 12
    assert seen == [1] * 16


def test_a_log_under_the_full_join_writes_changed_rows_alone(spark, monkeypatch):
    g = Graph.of(spark.createDataFrame([(n, n + 1, 1) for n in range(1, 6)], "src long, dst long, weight long"), symmetric=True)
    idle, pin = [], Pins.pin

    def spy(self, df, age=None):
        kept = pin(self, df, age)
        if "ran" in kept.columns:
            idle.append(kept.where("NOT ran").count())
        return kept

    monkeypatch.setattr(Pins, "pin", spy)
    got = vertex.connected_components(g, PlanHints(Join.FULL, GroupBy.HASH, store=Store.DELTA_LOG, partitions=2)).vertices
    assert {(r.vid, r.value) for r in got.collect()} == {(v, 1) for v in range(1, 7)}
    assert len(idle) > 3 and not any(idle)
