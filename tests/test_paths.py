"""Merged chains: order, ends, cycles, and how much is written for a long chain."""

import pytest
from pyspark.sql import functions as F

from bspflow.algos import structure


def test_chains_are_put_in_order(spark):
    nodes = spark.createDataFrame([(v, f"t{v}") for v in (7, 3, 9, 1, 4, 20)], "vid long, seq string")
    succ = spark.createDataFrame([(7, 3), (3, 9), (9, 1), (4, 99)], "vid long, next long")
    rows = {(r["head"], r.seq, r.length) for r in structure.merge_paths(nodes, succ).collect()}
    assert rows == {(7, "t7 t3 t9 t1", 4), (4, "t4", 1), (20, "t20", 1)}


def test_a_cycle_is_refused(spark):
    nodes = spark.createDataFrame([(v, "x") for v in range(3)], "vid long, seq string")
    succ = spark.createDataFrame([(v, (v + 1) % 3) for v in range(3)], "vid long, next long")
    with pytest.raises(RuntimeError, match="cycle"):
        structure.merge_paths(nodes, succ, 6)


def test_what_is_written_does_not_grow_with_the_square_of_a_chain(spark, monkeypatch):
    written, plain = [], structure.cut

    def cut(df):
        out = plain(df)
        written.append(max((len(str(r)) for r in out.collect()), default=0))
        return out

    monkeypatch.setattr(structure, "cut", cut)
    n = 300
    nodes = spark.range(n).select(F.col("id").alias("vid"), F.lit("word").alias("seq"))
    succ = spark.range(n - 1).select(F.col("id").alias("vid"), (F.col("id") + 1).alias("next"))
    assert [r.length for r in structure.merge_paths(nodes, succ).collect()] == [n]
    assert max(written) < 200  # no row of a round holds what follows it
