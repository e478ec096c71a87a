"""Baselines by the property that sets each apart.

process_mem    one fixed plan over all vertices, state held in memory, refused beyond a budget
process_ooc    the same plan with its state on disk, chosen beforehand
sorted_file    vertex files sorted by id and rewritten whole each step; messages must fit a budget
gas            edges partitioned by edge; gather over vertex mirrors, apply, refresh all mirrors
triplet        source-edge-target triplets made anew each step, messages joined back
semi_naive     only what changed is joined again (rank changes everywhere, so it is the full loop there)
mr_chain       nothing is reused: each step reads and writes everything
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..algos.vertex import UNIT
from ..model import Graph
from ..runtime.memory import state_bytes
from ..runtime.session import shared_folder


class OutOfBudget(RuntimeError):
    """The architecture can't hold its state."""


@dataclass
class Task:
    """One of the three methods as expressions over value, degree and the folded messages ``got``."""

    first: Column
    send: Column
    fold: str
    new: Column
    steps: int | None  # None: until nothing changes

    @property
    def folded(self) -> Column:
        return F.sum("m") if self.fold == "sum" else F.min("m")


def task(graph: Graph, name: str, source: int | None = None, steps: int = 5) -> Task:
    if name == "pagerank":
        n = graph.vertices.count()
        return Task(F.lit(UNIT // n).cast("long"), F.expr("value div degree"), "sum", F.expr(f"{(UNIT * 15 // 100) // n} + (coalesce(got, 0) * 85) div 100").cast("long"), steps - 1)
    if name == "sssp":
        return Task(F.when(F.col("vid") == source, 0).cast("long"), F.expr("value + 1"), "min", F.expr("least(value, got)"), None)
    return Task(F.col("vid"), F.col("value"), "min", F.expr("least(value, got)"), None)


def _start(graph: Graph, t: Task) -> DataFrame:
    degree = graph.edges.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("degree"))
    return graph.vertices.join(degree, "vid", "left").select("vid", F.coalesce("degree", F.lit(0)).alias("degree"), t.first.alias("value"), F.lit(True).alias("changed"))


def _apply(state: DataFrame, got: DataFrame, t: Task) -> DataFrame:
    rows = state.select("vid", "degree", F.col("value").alias("old"), "value").join(got, "vid", "left")
    return rows.select("vid", "degree", t.new.alias("value"), (~t.new.eqNullSafe(F.col("old"))).alias("changed"))


def _loop(graph: Graph, t: Task, messages, keep, changed_only: bool) -> DataFrame:
    state = keep(_start(graph, t))
    done = 0
    while t.steps is None or done < t.steps:
        sending = state.where("changed AND value IS NOT NULL") if changed_only and t.steps is None else state.where("value IS NOT NULL AND degree > 0")
        state = keep(_apply(state, messages(state, sending), t))
        done += 1
        if t.steps is None and not state.where("changed").limit(1).count():
            break
    return state.select("vid", "value")


def _files(graph: Graph, ordered: bool = False):
    """Keep a table by writing it out and reading it again."""
    root = f"{shared_folder(graph.spark)}/base-{uuid.uuid4().hex}"
    at = {"n": 0}

    def keep(df: DataFrame) -> DataFrame:
        at["n"] += 1
        path = f"{root}/{at['n']}"
        (df.repartition("vid").sortWithinPartitions("vid") if ordered else df).write.parquet(path)
        return graph.spark.read.parquet(path)

    return keep


def _checkpoints(graph: Graph):
    shared_folder(graph.spark)
    return lambda df: df.checkpoint(eager=True)


def _along(graph: Graph, t: Task):
    edges = graph.edges.select("src", "dst").persist()

    def messages(state: DataFrame, sending: DataFrame) -> DataFrame:
        rows = sending.select(F.col("vid").alias("src"), t.send.alias("m")).join(edges, "src")
        return rows.groupBy(F.col("dst").alias("vid")).agg(t.folded.alias("got"))

    return messages


def process_mem(graph: Graph, t: Task, budget: int | None = None) -> DataFrame:
    if budget is not None and state_bytes(graph) > budget:
        raise OutOfBudget("vertices and edges exceed the memory of the workers")
    return _loop(graph, t, _along(graph, t), _checkpoints(graph), changed_only=False)


def process_ooc(graph: Graph, t: Task, budget: int | None = None) -> DataFrame:
    return _loop(graph, t, _along(graph, t), _files(graph), changed_only=False)


def sorted_file(graph: Graph, t: Task, budget: int | None = None) -> DataFrame:
    if budget is not None and graph.edges.count() * 16 > budget:
        raise OutOfBudget("messages exceed the memory of the workers")
    return _loop(graph, t, _along(graph, t), _files(graph, ordered=True), changed_only=False)


def gas(graph: Graph, t: Task, budget: int | None = None) -> DataFrame:
    """Every edge is an endpoint of mirrors; gathers read both, and mirrors are sent out again each step."""
    if budget is not None and 2 * state_bytes(graph) > budget:
        raise OutOfBudget("edges and mirrors exceed the memory of the workers")
    edges = graph.edges.select("src", "dst").repartition("src", "dst").persist()

    def messages(state: DataFrame, sending: DataFrame) -> DataFrame:
        mirrors = sending.select(F.col("vid").alias("src"), t.send.alias("m"))
        return edges.join(mirrors, "src").groupBy(F.col("dst").alias("vid")).agg(t.folded.alias("got"))

    return _loop(graph, t, messages, _checkpoints(graph), changed_only=False)


def triplet(graph: Graph, t: Task, budget: int | None = None) -> DataFrame:
    """Edges are held by source; the view of both ends is made anew each step.

    States are files: a checkpoint carries the planner's size estimate, which a view that joins a state twice squares,
    until numbers of millions of digits take minutes and the driver's memory.
    """
    edges = graph.edges.select("src", "dst").repartition("src").persist()

    def messages(state: DataFrame, sending: DataFrame) -> DataFrame:
        view = edges.join(sending.select(F.col("vid").alias("src"), t.send.alias("m")), "src").join(state.select(F.col("vid").alias("dst"), F.col("value").alias("there")), "dst")
        return view.groupBy(F.col("dst").alias("vid")).agg(t.folded.alias("got"))

    try:
        return _loop(graph, t, messages, _files(graph), changed_only=False)
    finally:
        edges.unpersist()


def semi_naive(graph: Graph, t: Task, budget: int | None = None) -> DataFrame:
    return _loop(graph, t, _along(graph, t), _checkpoints(graph), changed_only=True)


def mr_chain(graph: Graph, t: Task, budget: int | None = None) -> DataFrame:
    keep = _files(graph)

    def messages(state: DataFrame, sending: DataFrame) -> DataFrame:
        edges = keep(graph.edges.select(F.col("src").alias("vid"), "dst"))
        rows = sending.select("vid", t.send.alias("m")).join(edges, "vid")
        return rows.groupBy(F.col("dst").alias("vid")).agg(t.folded.alias("got"))

    return _loop(graph, t, messages, keep, changed_only=False)


SYSTEMS = {"process_mem": process_mem, "process_ooc": process_ooc, "sorted_file": sorted_file, "gas": gas, "triplet": triplet, "semi_naive": semi_naive, "mr_chain": mr_chain}
