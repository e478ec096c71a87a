"""The superstep loop of column programs."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..model import Graph
from ..plans import combine as combining
from ..plans.hints import Join, PlanHints, Store
from ..plans.logical import active_set, apply_mutations, create_missing, deliver_full, is_active
from ..plans.storage import VertexStore
from ..program import Context, Program, Step
from .checkpoint import Checkpointer
from .gs import GlobalState
from .session import Pins, choose_partitions, scoped


@dataclass
class Result:
    """Final (vid, value), and one row of statistics a superstep."""

    vertices: DataFrame
    supersteps: int
    stats: list[dict] = field(default_factory=list)
    aggregates: dict = field(default_factory=dict)

    def stats_frame(self, spark) -> DataFrame:
        rows = [(s["superstep"], s["vertices"], s["ran"], s["live"], s["senders"], s["messages"], s["received"], s["seconds"]) for s in self.stats]
        return spark.createDataFrame(rows, "superstep long, vertices long, ran long, live long, senders long, messages long, received long, seconds double")


def load_state(graph: Graph, program: Program, partitions: int) -> DataFrame:
    """All vertices active, with their initial value and out-degree, partitioned and sorted by vid."""
    degree = graph.edges.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("degree"))
    rows = graph.vertices.join(degree, "vid", "left").withColumn("degree", F.coalesce("degree", F.lit(0)).cast("long"))
    value = program.initial().cast(program.value_type)
    return rows.select("vid", F.lit(False).alias("halt"), value.alias("value"), "degree").repartition(partitions, "vid").sortWithinPartitions("vid")


def load_topology(graph: Graph, partitions: int) -> DataFrame:
    """Edges where their source is, so that messages are made without an exchange."""
    return graph.edges.select("src", "dst", "weight").repartition(partitions, "src").sortWithinPartitions("src")


def run(graph: Graph, program: Program, hints: PlanHints = PlanHints(), max_supersteps: int | None = None, checkpoint: Checkpointer | None = None, checkpoint_when=None, resume: bool = False, stop_after: int | None = None, start: DataFrame | None = None) -> Result:
    """Run supersteps until all vertices have halted and no message is under way.

    One job a superstep: it delivers messages, computes, writes the step's table, and observes the step's one row of
    global state and counts on the way.
    Vertices and topology stay where they are; messages are the only exchange.  Adaptive execution is off inside
    the loop, as it forgets partitionings.  ``start`` is a state from an earlier job of a pipeline; ``stop_after``
    ends the loop early, as a failure would.  ``max_supersteps`` is for programs of a stated number of steps.
    """
    spark = graph.spark
    parts = hints.partitions or choose_partitions(spark)
    keep = {"spark.sql.adaptive.enabled": "false", "spark.sql.shuffle.partitions": str(parts), "spark.sql.autoBroadcastJoinThreshold": "-1"}
    keep |= combining.settings(hints.groupby, hints.connector)
    pins, stats = Pins(spark), []
    with scoped(spark, keep):
        topology = load_topology(graph, parts).persist()
        gs, found = GlobalState(), checkpoint.restore() if checkpoint and resume else None
        empty = spark.range(1).where("false").select(F.col("id").alias("vid"), F.lit(None).cast(program.payload_type).alias("payload")).repartition(parts, "vid")
        if found:
            gs, state, msg = found[0], *(d.repartition(parts, "vid").sortWithinPartitions("vid") for d in found[1:])
            state, msg = pins.pin(state), pins.pin(msg)
        else:
            state = start.repartition(parts, "vid").sortWithinPartitions("vid").withColumn("halt", F.lit(False)) if start is not None else load_state(graph, program, parts)
            state, msg = pins.pin(state), empty
        store = VertexStore(state, hints, pins.pin)
        live: DataFrame | None = None
        n_vertices = n_active = n_live = None
        all_live = not found
        try:
            while not gs.halt and (max_supersteps is None or gs.superstep <= max_supersteps):
                began = time.time()
                join = _join_for(hints, n_vertices, n_active)
                pins.age += 1
                if join is Join.LEFT:
                    if all_live:  # nothing to look for: the active set is everything
                        rows = store.read().withColumn("payload", F.lit(None).cast(program.payload_type)).withColumn("created", F.lit(False))
                    else:
                        if n_live == 0:
                            active = msg
                        else:
                            bare = live if live is not None else store.read().where(~F.col("halt")).select("vid")
                            active = active_set(bare, msg)
                        rows = store.probe(active).withColumn("created", F.lit(False))
                        if program.creates:
                            rows = rows.unionByName(create_missing(store.read(), active).withColumn("created", F.lit(True)))
                else:
                    current = store.read()
                    rows = deliver_full(current, msg).withColumn("created", F.lit(False))
                    if program.creates and gs.superstep > 1:
                        rows = rows.unionByName(create_missing(current, msg).withColumn("created", F.lit(True)))
                seen = Observation()
                logs = hints.store is Store.DELTA_LOG
                out = _compute(rows, program, gs, join)
                out = out.observe(seen, *_counts(program, out.columns))
                only_changed = (join is Join.LEFT or logs) and not all_live
                out = pins.pin(out.where("ran") if only_changed and join is Join.FULL else out)
                row = seen.get
                if only_changed:
                    n_vertices = row["vertices"] if join is Join.FULL else n_vertices + row["created"]
                    store.upsert(out.select("vid", "halt", "value", "degree"), row["ran"], n_vertices)
                    live = out.where("ran AND NOT halt").select("vid")
                else:
                    store.replace(out.select("vid", "halt", "value", "degree"))
                    live, n_vertices, all_live = None, row["vertices"], False
                n_live = row["live"]
                if row["mutated"]:
                    state = pins.pin(_mutated(store.read(), out.select(F.inline("mut")), topology, program).repartition(parts, "vid").sortWithinPartitions("vid"))
                    store.replace(state)
                    live, after = None, state.agg(F.count("*").alias("vertices"), F.count_if(~F.col("halt")).alias("live")).first()
                    n_vertices, n_live = after.vertices, after.live
                sent = row["messages"] > 0
                stats.append({"superstep": gs.superstep, "vertices": n_vertices, "ran": row["ran"], "live": row["live"], "senders": row["senders"], "messages": row["messages"], "received": row["received"], "join": join.value, "seconds": time.time() - began})
                senders = out.where("send IS NOT NULL").select("vid", "send")
                raw = topology.join(senders.hint("shuffle_hash"), F.col("vid") == F.col("src")) if join is Join.LEFT else senders.join(topology, F.col("vid") == F.col("src"))
                raw = raw.select(F.col("dst").alias("vid"), program.edge_payload(F.col("send"), F.col("weight")).cast(program.payload_type).alias("payload"))
                if "post" in out.columns:
                    raw = raw.unionByName(out.select(F.inline("post")).select("vid", F.col("payload").cast(program.payload_type).alias("payload")))
                msg = combining.combine(raw, program.combiner, hints.groupby, hints.connector, parts) if sent else empty
                n_active = n_live + min(row["messages"], n_vertices)
                aggregates = {k: row[f"agg_{k}"] for k in program.aggregators}
                halt = not sent and n_live == 0 or program.stop is not None and program.stop(aggregates)
                gs = gs.next(bool(halt), aggregates)
                if not store.deltas:
                    pins.drop_before(pins.age)
                due = checkpoint and checkpoint_when and (checkpoint_when(gs) if callable(checkpoint_when) else (gs.superstep - 1) % checkpoint_when == 0)
                if sent and not halt and (due or program.creates):
                    msg = pins.pin(msg)  # read twice: combine them once
                if due:
                    checkpoint.save(gs, store.read().select("vid", "halt", "value", "degree"), msg)
                if stop_after and gs.superstep > stop_after:
                    break
            final = store.read().select("vid", "value", "degree").checkpoint(eager=True)
        finally:
            store.release()
            pins.close()
            topology.unpersist()
    return Result(final, gs.superstep - 1, stats, gs.aggregates)


def _join_for(hints: PlanHints, n_vertices: int | None, n_active: int | None) -> Join:
    if hints.join is not Join.AUTO:
        return hints.join
    return Join.LEFT if n_vertices and n_active is not None and n_active / n_vertices < hints.sparse_below else Join.FULL


def _compute(rows: DataFrame, program: Program, gs: GlobalState, join: Join) -> DataFrame:
    """The user's columns on active rows; idle rows keep what they have and send nothing."""
    ctx = Context(gs.superstep, gs.aggregates, F.col("vid"), F.col("value"), F.col("payload"), F.col("degree"))
    step: Step = program.compute(ctx)
    ran = F.lit(True) if join is Join.LEFT else is_active()
    send = step.send if step.send is not None else F.lit(None)
    cols = [
        F.when(ran, step.halt).otherwise(F.col("halt")).alias("halt"),
        F.when(ran, step.value.cast(program.value_type)).otherwise(F.col("value")).alias("value"),
        F.when(ran & (F.col("degree") > 0), send).alias("send"),
        *[F.when(ran, step.aggregate.get(k, F.lit(None))).alias(f"c_{k}") for k in program.aggregators],
    ]
    cols += [F.when(ran, c).alias(name) for name, c in (("post", step.post), ("mut", step.mutate)) if c is not None]
    return rows.select("vid", "degree", ran.alias("ran"), F.col("payload").isNotNull().alias("received"), "created", *cols)


def _mutated(state: DataFrame, mutations: DataFrame, topology: DataFrame, program: Program) -> DataFrame:
    """All vertices after the mutations; an inserted one has the edges that the topology lists of its id."""
    asked = mutations.select(F.col("vid").alias("src")).distinct()
    degree = topology.join(asked, "src", "left_semi").groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("degree"))
    made = F.struct("vertex.value", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"))
    known = mutations.join(degree, "vid", "left").select("vid", "op", F.when(F.col("vertex").isNotNull(), made).alias("vertex"))
    return apply_mutations(state.select("vid", "halt", "value", "degree"), known, program.resolve)


def _counts(program: Program, columns: list[str]) -> list:
    told = {"ran": "ran", "live": "NOT halt", "senders": "send IS NOT NULL", "received": "received", "created": "created"}
    many = {name: f"coalesce(sum(if({name} IS NULL, 0, size({name}))), 0L)" if name in columns else "0L" for name in ("post", "mut")}
    counts = [F.expr("count(*) AS vertices"), F.expr(f"coalesce(sum(if(send IS NOT NULL, degree, 0L)), 0L) + {many['post']} AS messages")]
    counts.append(F.expr(f"{many['mut']} + count(*) * 0 AS mutated"))
    counts += [F.expr(f"count_if({c}) AS {k}") for k, c in told.items()]
    return counts + [fold(F.col(f"c_{k}")).alias(f"agg_{k}") for k, fold in program.aggregators.items()]
