"""Vertex programs: rank, shortest paths, components, reachability, spanning trees."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import Graph
from ..plans.combine import COUNT, MIN, STRUCT_MIN, SUM
from ..plans.hints import GroupBy, Join, PlanHints, Store
from ..program import Context, Program, Step
from ..runtime.loop import Result, run

#: Whole-number ranks count in units of this: exact in any engine, and the same in any order of addition.
UNIT = 1_000_000_000_000

RANK_PLAN = PlanHints(Join.FULL, GroupBy.HASH)
SPARSE_PLAN = PlanHints(Join.LEFT, GroupBy.HASH, store=Store.DELTA_LOG)
COMPONENT_PLAN = PlanHints(Join.AUTO, GroupBy.HASH)


def pagerank_program(n: int, steps: int, damping: float = 0.85, tol: float | None = None, dangling: str = "drop", fixed_point: bool = False) -> Program:
    """Each step sets rank = (1 - d) / n + d * received and sends rank / degree on; the first only sends 1 / n.

    ``dangling='redistribute'`` spreads the rank of vertices without edges over all through the aggregate.
    """
    pct = round(damping * 100)

    def compute(c: Context) -> Step:
        spread = c.aggregate("dangling") if dangling == "redistribute" else 0
        if fixed_point:
            got = F.coalesce(c.payload, F.lit(0)) + F.lit(int(spread or 0) // n)
            new = F.lit(UNIT // n) if c.superstep == 1 else F.lit((UNIT * (100 - pct) // 100) // n) + F.expr("0") + (got * pct - (got * pct) % 100) / 100
            new = new.cast("long")
            send = ((new - new % F.greatest(c.degree, F.lit(1))) / F.greatest(c.degree, F.lit(1))).cast("long")
        else:
            got = F.coalesce(c.payload, F.lit(0.0)) + F.lit(float(spread or 0.0) / n)
            new = F.lit(1.0 / n) if c.superstep == 1 else F.lit((1 - damping) / n) + F.lit(damping) * got
            send = new / c.degree
        last = c.superstep >= steps
        zero = F.lit(0) if fixed_point else F.lit(0.0)
        moved = F.abs(new - F.coalesce(c.value, zero))
        return Step(new, F.lit(last), F.lit(None) if last else send, {"delta": moved, "dangling": F.when(c.degree == 0, new).otherwise(zero)})

    kind = "long" if fixed_point else "double"
    stop = (lambda a: a.get("delta") is not None and float(a["delta"]) < tol) if tol is not None else None
    return Program("pagerank", kind, kind, SUM, lambda: F.lit(None), compute, aggregators={"delta": F.sum, "dangling": F.sum}, stop=stop)


def pagerank(graph: Graph, steps: int = 10, damping: float = 0.85, tol: float | None = None, dangling: str = "drop", fixed_point: bool = False, hints: PlanHints = RANK_PLAN, **more) -> Result:
    n = graph.vertices.count()
    return run(graph, pagerank_program(max(n, 1), steps, damping, tol, dangling, fixed_point), hints, max_supersteps=steps, **more)


def sssp_program(source: int, weighted: bool = False) -> Program:
    """Distances shrink; whoever's shrinks tells its neighbours; everyone halts until told."""

    def compute(c: Context) -> Step:
        told = F.when(c.vid == source, F.lit(0).cast("long")) if c.superstep == 1 else c.payload
        better = told.isNotNull() & (c.value.isNull() | (told < c.value))
        return Step(F.when(better, told).otherwise(c.value), F.lit(True), F.when(better, told), {"updated": better.cast("long")})

    along = (lambda s, w: s + w) if weighted else (lambda s, w: s + 1)
    return Program("sssp", "long", "long", MIN, lambda: F.lit(None), compute, along, {"updated": F.sum})


def sssp(graph: Graph, source: int, weighted: bool = False, hints: PlanHints = SPARSE_PLAN, max_supersteps: int | None = None, **more) -> Result:
    return run(graph, sssp_program(source, weighted), hints, max_supersteps, **more)


def sssp_parents(graph: Graph, source: int, weighted: bool = False, hints: PlanHints = SPARSE_PLAN, max_supersteps: int | None = None) -> DataFrame:
    """(vid, dist, parent): parent is the lowest neighbour on a shortest path; the source's is itself.  Weights are positive."""
    kind = "struct<dist:long,parent:long>"

    def compute(c: Context) -> Step:
        mine = F.struct(F.lit(0).cast("long").alias("dist"), F.lit(source).cast("long").alias("parent"))
        told = F.when(c.vid == source, mine) if c.superstep == 1 else F.when(c.vid != source, c.payload)
        closer = told.isNotNull() & (c.value.isNull() | (told["dist"] < c.value["dist"]))
        # an equal distance by a lower neighbour changes the parent alone, which is no news to others
        better = closer | (told.isNotNull() & (told < c.value))
        send = F.when(closer, F.struct(told["dist"].alias("dist"), c.vid.alias("parent")))
        return Step(F.when(better, told).otherwise(c.value), F.lit(True), send)

    def along(s: Column, w: Column) -> Column:
        return F.struct((s["dist"] + (w if weighted else F.lit(1).cast("long"))).alias("dist"), s["parent"].alias("parent"))

    program = Program("sssp_parents", kind, kind, STRUCT_MIN, lambda: F.lit(None), compute, along)
    found = run(graph, program, hints, max_supersteps).vertices.where("value IS NOT NULL")
    return found.select("vid", F.col("value.dist").alias("dist"), F.col("value.parent").alias("parent"))


def list_rank_walk(graph: Graph, hints: PlanHints = SPARSE_PLAN) -> DataFrame:
    """(vid, rank): steps to the end of a list of edges vid -> next, walked one link a superstep from the ends.

    The plain form that pointer jumping is held against: as many supersteps as the longest list has vertices.
    """
    back = Graph(graph.vertices, graph.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))

    def compute(c: Context) -> Step:
        if c.superstep == 1:  # whoever hears nothing of a next one is an end
            return Step(c.value, F.lit(False), F.lit(-1).cast("long"))
        rank = F.when(c.payload.isNull(), F.lit(0).cast("long")) if c.superstep == 2 else c.payload + 1
        return Step(F.coalesce(c.value, rank), F.lit(True), rank)

    got = run(back, Program("list_walk", "long", "long", MIN, lambda: F.lit(None), compute), hints).vertices
    return got.select("vid", F.col("value").alias("rank"))


def highest_degree(graph: Graph) -> int:
    """The vertex with most edges, the lowest of several."""
    row = graph.edges.groupBy("src").count().orderBy(F.desc("count"), "src").first()
    return row.src if row else -1


def components_program() -> Program:
    """Smallest vertex id heard of."""

    def compute(c: Context) -> Step:
        low = c.vid if c.superstep == 1 else F.least(c.value, c.payload, *([c.vid]))
        new = F.when(c.value.isNull(), low).otherwise(F.least(c.value, low))
        changed = c.value.isNull() | (new < c.value)
        return Step(new, F.lit(True), F.when(changed, new), {"changed": changed.cast("long")})

    return Program("components", "long", "long", MIN, lambda: F.lit(None), compute, aggregators={"changed": F.sum})


def connected_components(graph: Graph, hints: PlanHints = COMPONENT_PLAN, max_supersteps: int | None = None, creates: bool = False, **more) -> Result:
    """Labels by minimum propagation; the edges must have both directions."""
    program = components_program()
    program.creates = creates
    return run(graph, program, hints, max_supersteps, **more)


def reachability(graph: Graph, sources: list[int], targets: list[int] | None = None, hints: PlanHints = SPARSE_PLAN, max_supersteps: int | None = None) -> DataFrame:
    """(vid, hops) of what can be reached; with targets, stops when all are reached."""

    def compute(c: Context) -> Step:
        told = F.when(c.vid.isin(sources), F.lit(0).cast("long")) if c.superstep == 1 else c.payload
        new = c.value.isNull() & told.isNotNull()
        hit = (new & c.vid.isin(targets)).cast("long") if targets else F.lit(0).cast("long")
        seen = F.lit(int(c.aggregate("hit")))
        return Step(F.when(new, told).otherwise(c.value), F.lit(True), F.when(new, told), {"hit": hit, "seen": seen})

    total = {"n": 0}

    def stop(a: dict) -> bool:
        total["n"] += int(a.get("hit") or 0)
        return targets is not None and total["n"] >= len(set(targets))

    program = Program("reach", "long", "long", MIN, lambda: F.lit(None), compute, lambda s, w: s + 1, {"hit": F.sum, "seen": F.max}, stop=stop)
    return run(graph, program, hints, max_supersteps).vertices.where("value IS NOT NULL").select("vid", F.col("value").alias("hops"))


def bfs_tree(graph: Graph, root: int, hints: PlanHints = SPARSE_PLAN, max_supersteps: int | None = None) -> DataFrame:
    """(vid, parent, depth): parent is the lowest neighbour one nearer to the root; the root's is itself."""

    def compute(c: Context) -> Step:
        mine = F.struct(F.lit(0).cast("long").alias("depth"), F.lit(root).cast("long").alias("parent"))
        told = F.when(c.vid == root, mine) if c.superstep == 1 else c.payload
        new = c.value.isNull() & told.isNotNull()
        send = F.when(new, F.struct((told["depth"] + 1).alias("depth"), c.vid.alias("parent")))
        return Step(F.when(new, told).otherwise(c.value), F.lit(True), send)

    kind = "struct<depth:long,parent:long>"
    program = Program("bfs", kind, kind, STRUCT_MIN, lambda: F.lit(None).cast(kind), compute)
    found = run(graph, program, hints, max_supersteps).vertices.where("value IS NOT NULL")
    return found.select("vid", F.col("value.parent").alias("parent"), F.col("value.depth").alias("depth"))


def degree_aggregates(graph: Graph, hints: PlanHints = RANK_PLAN) -> dict:
    """Least, largest and total out-degree through the global aggregate."""

    def compute(c: Context) -> Step:
        return Step(c.degree, F.lit(True), None, {"low": c.degree, "high": c.degree, "total": c.degree, "n": F.lit(1).cast("long")})

    program = Program("degrees", "long", "long", COUNT, lambda: F.lit(None), compute, aggregators={"low": F.min, "high": F.max, "total": F.sum, "n": F.sum})
    return run(graph, program, hints, 1).aggregates


def message_fold(graph: Graph, combiner, payload: Column | None = None, payload_type: str = "long", hints: PlanHints = RANK_PLAN) -> DataFrame:
    """(vid, payload): what each vertex receives if all send their id (or ``payload``) once, under a combiner."""

    def compute(c: Context) -> Step:
        send = payload if payload is not None else c.vid
        return Step(c.payload if c.superstep == 2 else F.lit(None), F.lit(True), send if c.superstep == 1 else None)

    got = run(graph, Program("fold", payload_type, payload_type, combiner, lambda: F.lit(None), compute), hints, 2)
    return got.vertices.where("value IS NOT NULL").select("vid", F.col("value").alias("payload"))
