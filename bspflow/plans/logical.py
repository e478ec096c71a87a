"""The flows of a superstep as DataFrame builders: delivery, creation of missing vertices, the active set, mutations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def deliver_full(state: DataFrame, msg: DataFrame) -> DataFrame:
    """All vertices with their message, if any.  The left join keeps the vertices' partitioning, as a full outer
    join would not; messages to missing vertices are ``create_missing``'s."""
    return state.join(msg, "vid", "left")


def create_missing(state: DataFrame, msg: DataFrame) -> DataFrame:
    """Vertices that messages call into being: all fields null, active."""
    new = msg.join(state.select("vid"), "vid", "left_anti")
    blank = [F.lit(None).cast(f.dataType).alias(f.name) for f in state.schema.fields if f.name not in ("vid", "halt", "degree")]
    degree = [F.lit(0).cast("long").alias("degree")] if "degree" in state.columns else []
    return new.select("vid", F.lit(False).alias("halt"), *blank, *degree, "payload")


def literal_full_outer(state: DataFrame, msg: DataFrame) -> DataFrame:
    """The definition, kept to test the partition-preserving form against."""
    rows = state.join(msg, "vid", "full_outer")
    return rows.withColumn("halt", F.coalesce("halt", F.lit(False)))


def active_set(live: DataFrame, msg: DataFrame) -> DataFrame:
    """Live vertices and receivers, once each; a message takes precedence over a bare live entry."""
    bare = live.select("vid", F.lit(None).cast(msg.schema["payload"].dataType).alias("payload"))
    return msg.select("vid", "payload").unionByName(bare).groupBy("vid").agg(F.first("payload", ignorenulls=True).alias("payload"))


def is_active(halt: str = "halt", payload: str = "payload") -> Column:
    return ~F.col(halt) | F.col(payload).isNotNull()


def resolve_default(ops: str = "ops") -> Column:
    """Of all mutations of a vertex the insertion with the smallest vertex, else its deletion."""
    inserts = F.array_sort(F.filter(ops, lambda m: m["op"] == "I"))
    return F.when(F.size(inserts) > 0, F.element_at(inserts, 1)).otherwise(F.element_at(ops, 1))


def apply_mutations(state: DataFrame, mutations: DataFrame, resolve=resolve_default) -> DataFrame:
    """``mutations``(vid, op, vertex) resolved per vertex, deletions before insertions.

    The whole group is needed at once, so there is no partial aggregation: rows are dealt by vid first.
    """
    ops = mutations.repartition("vid").groupBy("vid").agg(F.collect_list(F.struct("op", "vertex")).alias("ops"))
    one = ops.select("vid", resolve("ops").alias("m"))
    kept = state.join(one.select("vid"), "vid", "left_anti")
    new = one.where("m.op = 'I'").select("vid", F.lit(False).alias("halt"), "m.vertex.*")
    return kept.unionByName(new, allowMissingColumns=True)
