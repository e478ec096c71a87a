"""Vertex programs as columns: what a user writes for one superstep stays inside Spark's code generation."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F

from .plans.combine import Combiner
from .plans.logical import resolve_default


@dataclass
class Context:
    """What compute sees: columns of the vertex and its combined message, and the global state as constants."""

    superstep: int
    aggregates: dict[str, object]
    vid: Column
    value: Column
    payload: Column
    degree: Column

    def aggregate(self, name: str, default=0):
        got = self.aggregates.get(name)
        return default if got is None else got


@dataclass
class Step:
    """What compute gives: the new value and halt flag, a payload to send (null: none), contributions to aggregates.

    ``post`` is an array of ``letter``s to vertices of any id; ``mutate`` an array of ``insertion``s and ``deletion``s,
    which are resolved per vertex and show in the next superstep.
    """

    value: Column
    halt: Column
    send: Column | None = None
    aggregate: dict[str, Column] = field(default_factory=dict)
    post: Column | None = None
    mutate: Column | None = None


@dataclass
class Program:
    """``edge_payload(send, weight)`` is the message along an edge; ``aggregators`` fold contributions of active vertices."""

    name: str
    value_type: str
    payload_type: str
    combiner: Combiner
    initial: Callable[[], Column]
    compute: Callable[[Context], Step]
    edge_payload: Callable[[Column, Column], Column] = lambda send, weight: send
    aggregators: dict[str, Callable[[Column], Column]] = field(default_factory=dict)
    #: messages may go to vertices that don't exist, which creates them
    creates: bool = False
    #: stop when this holds of the aggregates, besides the usual end
    stop: Callable[[dict], bool] | None = None
    #: a column over all mutations of a vertex that gives the one to apply
    resolve: Callable = resolve_default


def letter(vid: Column, payload: Column) -> Column:
    """A message to the vertex ``vid``, whether an edge leads there or not."""
    return F.struct(vid.cast("long").alias("vid"), payload.alias("payload"))


def insertion(vid: Column, value: Column) -> Column:
    """A mutation that makes the vertex ``vid`` with this value, active; its edges are those listed of its id."""
    return F.struct(vid.cast("long").alias("vid"), F.lit("I").alias("op"), F.struct(value.alias("value")).alias("vertex"))


def deletion(vid: Column, value_type: str) -> Column:
    """A mutation that takes the vertex ``vid`` away."""
    return F.struct(vid.cast("long").alias("vid"), F.lit("D").alias("op"), F.lit(None).cast(f"struct<value:{value_type}>").alias("vertex"))


def sum_of(c: Column) -> Column:
    return F.sum(c)
