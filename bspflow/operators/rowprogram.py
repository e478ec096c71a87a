"""Vertex programs in Python, for what columns can't say: edge edits, messages to any vertex, insertions, deletions.

Vertices are nested rows.  A superstep joins them with listed messages, runs ``compute`` on active rows in Arrow
batches, and takes the new rows, messages and mutations out of its output.  Python loses partitionings, so only this
output is dealt again; mutations resolve per vertex, deletions before insertions, and show in the next superstep.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import count

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Graph
from ..plans.logical import apply_mutations, create_missing, resolve_default
from ..runtime.session import Pins, choose_partitions, scoped


@dataclass
class Vertex:
    vid: int
    value: object
    edges: list[tuple[int, int]]


class Out:
    """What compute hands over besides the vertex itself."""

    def __init__(self):
        self.messages, self.mutations, self.halted = [], [], False

    def send(self, vid: int, payload) -> None:
        self.messages.append((vid, payload))

    def halt(self) -> None:
        self.halted = True

    def add_vertex(self, vid: int, value=None, edges=()) -> None:
        self.mutations.append((vid, "I", value, list(edges)))

    def remove_vertex(self, vid: int) -> None:
        self.mutations.append((vid, "D", None, None))


@dataclass
class RowProgram:
    """``compute(vertex, messages, global_state, out)``; ``resolve`` is a column over the mutations of a vertex."""

    name: str
    value_type: str
    payload_type: str
    compute: Callable
    resolve: Callable = resolve_default
    initial: object = None


def _runner(compute: Callable, superstep: int, out_schema: pa.Schema):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                v = Vertex(r["vid"], r["value"], [(e["dst"], e["value"]) for e in r["edges"] or []])
                out = Out()
                compute(v, r["payload"] or [], {"superstep": superstep}, out)
                edges = [{"dst": a, "value": b} for a, b in v.edges]
                muts = [{"vid": i, "op": op, "vertex": None if op == "D" else {"value": x, "edges": [{"dst": a, "value": b} for a, b in es]}} for i, op, x, es in out.mutations]
                rows.append({"vid": v.vid, "halt": out.halted, "value": v.value, "edges": edges, "out": [{"vid": i, "payload": p} for i, p in out.messages], "mut": muts})
            yield pa.RecordBatch.from_pylist(rows, schema=out_schema)

    return run


def run_rows(graph: Graph, program: RowProgram, max_supersteps: int | None = None) -> DataFrame:
    """Supersteps until all halt and no message is under way -> (vid, halt, value, edges)."""
    from pyspark.sql.pandas.types import to_arrow_schema

    spark = graph.spark
    parts = choose_partitions(spark)
    edge = "array<struct<dst:long,value:long>>"
    kind = f"vid long, halt boolean, value {program.value_type}, edges {edge}, out array<struct<vid:long,payload:{program.payload_type}>>, mut array<struct<vid:long,op:string,vertex:struct<value:{program.value_type},edges:{edge}>>>"
    out_schema = to_arrow_schema(spark.createDataFrame([], kind).schema)
    pins = Pins(spark)
    with scoped(spark, {"spark.sql.adaptive.enabled": "false", "spark.sql.shuffle.partitions": str(parts)}):
        lists = graph.edges.groupBy(F.col("src").alias("vid")).agg(F.array_sort(F.collect_list(F.struct("dst", F.col("weight").alias("value")))).alias("edges"))
        state = graph.vertices.select("vid").join(lists, "vid", "left")
        state = pins.pin(state.select("vid", F.lit(False).alias("halt"), F.lit(program.initial).cast(program.value_type).alias("value"), F.coalesce("edges", F.array().cast(edge)).alias("edges")))
        msg = spark.createDataFrame([], f"vid long, payload array<{program.payload_type}>")
        for superstep in count(1) if max_supersteps is None else range(1, max_supersteps + 1):
            pins.age += 1
            rows = state.join(msg, "vid", "left").unionByName(create_missing(state, msg))
            active = rows.where("NOT halt OR payload IS NOT NULL")
            out = pins.pin(active.select("vid", "value", "edges", "payload").mapInArrow(_runner(program.compute, superstep, out_schema), kind))
            changed = out.select("vid", "halt", "value", "edges")
            state = state.join(changed.select("vid"), "vid", "left_anti").unionByName(changed)
            muts = out.select(F.inline("mut"))
            counts = out.agg(F.sum(F.size("out")).alias("sent"), F.sum(F.size("mut")).alias("mutated")).first()
            if counts.mutated:
                state = apply_mutations(state, muts, program.resolve)
            state = pins.pin(state)
            msg = out.select(F.inline("out")).groupBy("vid").agg(F.array_sort(F.collect_list("payload")).alias("payload"))
            if not counts.sent and not state.where("NOT halt").limit(1).count():
                break
            pins.drop_before(pins.age)
        final = state.checkpoint(eager=True)
        pins.close()
    return final
