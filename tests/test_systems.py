"""Baselines: what their plans carry from step to step."""

from bspflow.baselines.systems import SYSTEMS, task
from bspflow.model import Graph


def test_size_estimates_of_triplets_do_not_grow_with_the_steps(spark):
    n = 9
    edges = spark.createDataFrame([(a, a + 1, 1) for a in range(n)], "src long, dst long, weight long")
    g = Graph.of(edges, symmetric=True)
    got = SYSTEMS["triplet"](g, task(g, "sssp", 0))
    assert {(r.vid, r.value) for r in got.collect()} == {(v, v) for v in range(n + 1)}
    size = str(got._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    assert len(size) < 150  # digits: they doubled with each step
