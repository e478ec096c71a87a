"""Methods whose Spark form is a few joins, windows or doubling rounds: triangles, cliques, sampling, tours, ranks,
orders, bi-connected and strongly connected components, closure, recommendation, scaling, statistics."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from contextvars import ContextVar
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import Graph
from ..runtime.session import shared_folder


#: Hops of a propagation in one job: more work a job, fewer jobs.
HOPS = 3
#: Folders of the tables cut since ``kept`` began.
_CUTS: ContextVar[list[str] | None] = ContextVar("cuts", default=None)


def cut(df: DataFrame) -> DataFrame:
    """A table written into the shared folder, so that rounds don't build on each other's plans.

    A checkpoint would carry the planner's size estimate, which a self-join squares: its digits double each round, and
    after a dozen rounds planning takes seconds. Files have their true size, by which Spark also picks joins.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/cut-{uuid.uuid4().hex}"
    # unions of rounds would add up partitions
    df.coalesce(int(spark.conf.get("spark.sql.shuffle.partitions"))).write.parquet(path)
    if (held := _CUTS.get()) is not None:
        held.append(path)
    return spark.read.schema(df.schema).parquet(path)


def kept(make: Callable[[], tuple[DataFrame, ...]], instead_of: tuple[DataFrame, ...] = ()) -> tuple[DataFrame, ...]:
    """``make()``'s tables.  The files of other tables cut on the way, and of those they stand ``instead_of``, are deleted."""
    read = lambda tables: {f.rpartition("/")[0] for df in tables for f in df.inputFiles()}
    name = lambda path: path.rpartition("/")[2]
    outer = _CUTS.get()
    token = _CUTS.set([])
    try:
        out = make()
        made = _CUTS.get()
    finally:
        _CUTS.reset(token)
    still = {name(path) for path in read(out)}
    if outer is not None:
        outer.extend(path for path in made if name(path) in still)
    jvm = out[0].sparkSession.sparkContext._jvm
    for path in [*made, *read(instead_of)]:
        if name(path) not in still and name(path).startswith("cut-"):
            folder = jvm.org.apache.hadoop.fs.Path(path)
            folder.getFileSystem(out[0].sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)
    jvm.System.gc()  # Spark deletes a shuffle's files once the driver's garbage is collected
    return out


# ---------------------------------------------------------------- triangles, cliques, recommendation


def oriented(pairs: DataFrame) -> DataFrame:
    """Each undirected pair once, from the vertex of lower (degree, id): out-degrees stay below sqrt(2 E)."""
    both = pairs.select("src", "dst").union(pairs.select("dst", "src")).toDF("src", "dst").where("src <> dst").distinct()
    degree = both.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("d"))
    rows = both.join(degree.toDF("src", "ds"), "src").join(degree.toDF("dst", "dd"), "dst")
    return rows.where("ds < dd OR (ds = dd AND src < dst)").select("src", "dst")


def _triangles_of(key: tuple, rows: pa.Table) -> pa.Table:
    """Triangles of oriented edges whose corners have the three colours of the key."""
    src, dst, cs, cd = (rows[c].to_numpy() for c in ("src", "dst", "cs", "cd"))
    by = np.lexsort((dst, src))
    src, dst, cs, cd = src[by], dst[by], cs[by], cd[by]
    ids, n = np.unique(np.concatenate([src, dst]), return_inverse=True)
    a, b = n[: len(src)], n[len(src) :]
    known = np.sort(np.minimum(a, b) * len(ids) + np.maximum(a, b))
    rest = np.searchsorted(a, a, side="right") - np.arange(len(a)) - 1
    upto, want, out = np.cumsum(rest), sorted(k.as_py() for k in key), []
    at = 0
    while at < len(a):
        end = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + 2_000_000, side="right")))
        first = np.repeat(np.arange(at, end), rest[at:end])
        second = first + 1 + np.arange(len(first)) - np.repeat(upto[at:end] - rest[at:end] - (upto[at - 1] if at else 0), rest[at:end])
        own = (np.sort(np.stack([cs[first], cd[first], cd[second]]), axis=0) == np.array(want)[:, None]).all(axis=0)
        first, second = first[own], second[own]
        low, high = np.minimum(b[first], b[second]), np.maximum(b[first], b[second])
        asked = low * len(ids) + high
        hit = known[np.minimum(np.searchsorted(known, asked), len(known) - 1)] == asked
        out.append((src[first[hit]], dst[first[hit]], dst[second[hit]]))
        at = end
    return pa.table({c: pa.array(np.concatenate([x[i] for x in out]) if out else np.zeros(0, np.int64), pa.int64()) for i, c in enumerate("abc")})


def triangles(pairs: DataFrame, edges_a_group: int = 300_000) -> DataFrame:
    """(a, b, c) of every triangle once.

    Vertices have one of p colours, and an edge goes to the p groups of three colours that hold its own two.  A group
    finds the triangles of just its colours, so edges are sent p times and pairs of a vertex's edges not at all.
    """
    e = cut(oriented(pairs))
    p = max(1, round((e.count() / edges_a_group) ** 0.5))
    colour = lambda c: F.pmod(F.xxhash64(c), F.lit(p)).cast("int")
    dealt = e.select("src", "dst", colour("src").alias("cs"), colour("dst").alias("cd")).withColumn("third", F.explode(F.sequence(F.lit(0), F.lit(p - 1))))
    met = dealt.withColumn("of", F.array_sort(F.array("cs", "cd", "third"))).select("src", "dst", "cs", "cd", *[F.col("of")[i].alias(f"k{i}") for i in range(3)])
    return met.groupBy("k0", "k1", "k2").applyInArrow(_triangles_of, "a long, b long, c long")


def triangle_count(pairs: DataFrame) -> DataFrame:
    """(vid, n): triangles of each vertex that has any."""
    return triangles(pairs).select(F.explode(F.array("a", "b", "c")).alias("vid")).groupBy("vid").agg(F.count("*").alias("n"))


#: Neighbours in the lists that a block of vertices holds.
BLOCK = 4_000_000


def _masks(row: np.ndarray, bit: np.ndarray, width: int) -> Iterator[tuple[int, int]]:
    """(row, its bits as a number) of the rows that have any; ``row`` is sorted."""
    rows, first = np.unique(row, return_index=True)
    step = max(1, (1 << 26) // width)
    for at in range(0, len(rows), step):
        some = slice(first[at], first[at + step] if at + step < len(rows) else len(row))
        packed = np.zeros((min(step, len(rows) - at), -(-width // 8)), np.uint8)
        which = np.searchsorted(rows, row[some]) - at
        np.bitwise_or.at(packed, (which, bit[some] >> 3), (1 << (bit[some] & 7)).astype(np.uint8))
        yield from zip(rows[at : at + step].tolist(), (int.from_bytes(x.tobytes(), "little") for x in packed), strict=True)


def _enumerated(near: list[int], closed: set[int]) -> Iterator[list[int]]:
    """Maximal cliques among all of ``near``'s vertices that no closed one extends; pivoting enumeration.

    Sets of vertices are bits of numbers.  A closed vertex matters by its neighbours among the open ones alone, so
    those with equal ones are one, and one with all of them ends a branch.
    """

    def entered(open_: int, closed: set[int]) -> list:
        most, pivot = max(((x.bit_count(), x) for x in closed), default=(-1, 0))
        whole, rest = open_.bit_count() - 1, open_
        while rest and most < whole:
            low = rest & -rest
            rest ^= low
            x = near[low.bit_length() - 1] & open_
            if x.bit_count() > most:
                most, pivot = x.bit_count(), x
        return [open_, closed, open_ & ~pivot]

    every = (1 << len(near)) - 1
    if every in closed:
        return
    members, frames = [], [entered(every, closed)]
    while frames:
        frame = frames[-1]
        open_, closed, branch = frame
        if not branch:
            frames.pop()
            if members:
                members.pop()
            continue
        low = branch & -branch
        at = low.bit_length() - 1
        frame[0], frame[2] = open_ ^ low, branch ^ low
        on = near[at] & open_
        if on:
            inside = {x & on for x in closed if x & low}
            closed.add(on)
            if on not in inside:
                inside.discard(0)
                members.append(at)
                frames.append(entered(on, inside))
        elif not any(x & low for x in closed):
            yield [*members, at]


def _cliques_of(key: tuple[pa.Scalar, ...], rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Maximal cliques whose first member, in degeneracy order, is one of the block's own vertices."""
    ids, own, many, flat = [], [], [], []
    for batch in rows:
        later = batch.column("later")
        ids.append(batch.column("vid").to_numpy())
        own.append(batch.column("own").to_numpy(zero_copy_only=False))
        many.append(later.value_lengths().to_numpy())
        flat.append(later.flatten().to_numpy())
    ids, own, lens, flat = (np.concatenate(x) for x in (ids, own, many, flat))
    names = np.unique(np.concatenate([ids, flat]))
    src, to = np.searchsorted(names, ids), np.searchsorted(names, flat).astype(np.int32)
    del flat
    first, many = np.zeros(len(names), np.int64), np.zeros(len(names), np.int64)
    first[src], many[src] = np.cumsum(lens) - lens, lens
    mine = np.zeros(len(names), bool)
    mine[src[own]] = True
    at = np.flatnonzero(mine[to])
    at = at[np.argsort(to[at], kind="stable")]
    came = np.repeat(src, lens).astype(np.int32)[at]
    ends = np.searchsorted(to[at], np.arange(len(names) + 1))
    place, out, held = np.full(len(names), -1, np.int32), [], 0

    def told() -> pa.RecordBatch:
        owner, found = zip(*out, strict=True)
        members = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, found)]), pa.int32()), pa.array(np.concatenate(found)))
        return pa.RecordBatch.from_arrays([pa.array(owner, pa.int64()), members], names=["owner", "members"])

    for v in np.flatnonzero(mine):
        after = np.sort(to[first[v] : first[v] + many[v]])
        beside = np.concatenate([after, came[ends[v] : ends[v + 1]]])
        place[after] = np.arange(len(after))
        n = many[beside]
        upto = np.cumsum(n)
        bit = place[to[np.repeat(first[beside] - (upto - n), n) + np.arange(upto[-1])]]
        place[after] = -1
        hit = np.flatnonzero(bit >= 0)
        row, bit = np.searchsorted(upto, hit, side="right"), bit[hit]
        inner = row < len(after)
        a, b = np.concatenate([row[inner], bit[inner]]), np.concatenate([bit[inner], row[inner]])
        by = np.argsort(a, kind="stable")
        near = [0] * len(after)
        for i, x in _masks(a[by], b[by], len(after)):
            near[i] = x
        closed = {x for _, x in _masks(row[~inner], bit[~inner], len(after))}
        for members in _enumerated(near, closed):
            out.append((names[v], np.sort(names[np.append(after[members], v)])))
            held += len(members) + 1
            if held >= 100_000:
                yield told()
                out, held = [], 0
    if out:
        yield told()


def maximal_cliques(pairs: DataFrame, most: int | None = None) -> DataFrame:
    """(size, members): every maximal clique of at least two vertices once, members joined in order.

    Vertices are dealt to blocks.  A vertex's later neighbours in the degeneracy order, a list, go once to each block
    that has the vertex or a neighbour of it; so a block has all links among the neighbours of its own vertices, and
    enumerates the cliques that these come first in.  Cliques that an earlier neighbour would extend are not maximal
    and are left out.  There are so many blocks that the lists of one hold some ``BLOCK`` neighbours on the average.
    """
    e = cut(oriented(pairs))
    sides = e.select(F.col("src").alias("vid"), F.lit(1).alias("out")).union(e.select("dst", F.lit(0))).groupBy("vid").agg(F.sum("out").alias("l"), (F.count("*") + 1).alias("to"))
    sizes = [int(e.sparkSession.conf.get("spark.sql.shuffle.partitions")) << i for i in range(1, 20)]
    sent = sides.agg(*[F.sum(F.col("l") * F.least("to", F.lit(n))).alias(str(n)) for n in sizes]).first()
    blocks = next((n for n, x in zip(sizes, sent, strict=True) if (x or 0) <= n * BLOCK), sizes[-1])
    block = lambda c: F.pmod(F.xxhash64(c), F.lit(blocks)).cast("int")
    homes = e.select("src", block("dst").alias("block")).union(e.select("dst", block("src"))).union(e.select("src", block("src"))).distinct()
    later = e.groupBy("src").agg(F.collect_list("dst").alias("later"))
    lists = homes.join(later, "src").select("block", F.col("src").alias("vid"), (F.col("block") == block("src")).alias("own"), "later")
    found = lists.groupBy("block").applyInArrow(_cliques_of, "owner long, members array<long>")
    sized = found.select(F.size("members").cast("long").alias("size"), F.array_join(F.transform("members", lambda x: x.cast("string")), ",").alias("members"))
    return sized.where(F.col("size") <= most) if most else sized


def recommend(pairs: DataFrame, k: int = 3) -> DataFrame:
    """(vid, candidate, common, rn): the k non-neighbours with most common neighbours, ties to the lower id.

    Vertices with equal neighbours are one class, named by its smallest.  Each class needs its best ``k + 1 + degree``
    candidates, as its members and their neighbours drop out.  Two classes that share two neighbours or more meet at
    one that is not the heaviest of either, and are counted there; of those that share one alone, only the lowest of
    each neighbour can count.  So no hub pairs all that lie around it.
    """
    both = cut(pairs.select("src", "dst").union(pairs.select("dst", "src")).toDF("src", "dst").distinct())
    sets = both.groupBy(F.col("src").alias("vid")).agg(F.array_sort(F.collect_list("dst")).alias("near"))
    alike = Window.partitionBy("near")
    members = cut(sets.select("vid", F.min("vid").over(alike).alias("cls"), F.row_number().over(alike.orderBy("vid")).alias("pos"), F.size("near").alias("d"), F.count("*").over(alike).cast("int").alias("size")))
    classes = members.where("pos = 1").select("cls", "size", "d", (F.col("d") + k + 1).alias("need"))
    held = both.join(classes.select(F.col("cls").alias("src"), "need"), "src").select(F.col("src").alias("cls"), F.col("dst").alias("mid"), "need")
    held = cut(held.withColumn("at", F.row_number().over(Window.partitionBy("mid").orderBy("cls"))).withColumn("n", F.count("*").over(Window.partitionBy("mid")).cast("int")))
    last = cut(held.groupBy("cls").agg(F.max(F.struct("n", "mid")).alias("x")).select("cls", F.col("x.mid").alias("mid")))
    light = cut(held.select("cls", "mid").join(last, ["cls", "mid"], "left_anti"))
    met = cut(light.toDF("a", "mid").join(light.toDF("b", "mid"), "mid").where("a < b").groupBy("a", "b").agg(F.count("*").alias("common")))
    ends = met.join(last.toDF("a", "la"), "a").join(last.toDF("b", "lb"), "b")
    mine, theirs = held.select(F.col("cls").alias("b"), F.col("mid").alias("la"), F.lit(1).alias("x")), held.select(F.col("cls").alias("a"), F.col("mid").alias("lb"), F.lit(1).alias("y"))
    told = ends.join(mine, ["b", "la"], "left").join(theirs, ["a", "lb"], "left")
    told = cut(told.select("a", "b", (F.col("common") + F.coalesce("x", F.lit(0)) + F.when(F.col("la") != F.col("lb"), F.coalesce("y", F.lit(0))).otherwise(0)).alias("common")))
    lowest = held.select("cls", "mid", F.explode(F.sequence(F.lit(1), F.least("need", "n"))).alias("at")).join(held.select("mid", "at", F.col("cls").alias("b")), ["mid", "at"]).where("cls <> b")
    found = told.union(told.select("b", "a", "common")).union(lowest.select("cls", "b", F.lit(1).cast("long"))).union(classes.where("size > 1").select("cls", "cls", F.col("d").cast("long")))
    best = found.groupBy("a", "b").agg(F.max("common").alias("common")).join(classes.select(F.col("cls").alias("a"), "need"), "a")
    best = best.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("common"), "b"))).where("r <= need")
    best = best.join(classes.select(F.col("cls").alias("b"), "size"), "b").withColumn("pos", F.explode(F.sequence(F.lit(1), F.least("need", "size"))))
    names = best.join(members.select(F.col("cls").alias("b"), "pos", F.col("vid").alias("candidate")), ["b", "pos"])
    names = names.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("common"), "candidate"))).where("r <= need")
    new = names.select(F.col("a").alias("cls"), "candidate", "common").join(members.select("cls", "vid"), "cls").where("vid <> candidate").join(both.toDF("vid", "candidate"), ["vid", "candidate"], "left_anti")
    order = Window.partitionBy("vid").orderBy(F.desc("common"), "candidate")
    return new.select("vid", "candidate", "common").withColumn("rn", F.row_number().over(order).cast("long")).where(F.col("rn") <= k)


# ---------------------------------------------------------------- sampling and scaling


def random_walk_sample(edges: DataFrame, seeds: DataFrame, walkers: int, steps: int, seed: int = 1, restart_in: int = 7) -> DataFrame:
    """(src, dst) of the sub-graph induced by what ``walkers`` walks of ``steps`` steps visit.

    Next hops are picked by MD5 of (seed, walker, step) among the neighbours in order, so any engine can check them;
    every ``restart_in``-th draw, or a vertex without edges, sends a walker back to its start.
    """
    order = Window.partitionBy("src").orderBy("dst")
    listed = edges.select("src", "dst", (F.row_number().over(order) - 1).alias("i")).withColumn("n", F.count("*").over(Window.partitionBy("src")))
    listed = cut(listed)
    degree = listed.where("i = 0").select("src", "n")
    starts = seeds.orderBy(F.md5(F.concat(F.lit(f"{seed}:"), F.col("vid").cast("string")).cast("binary")), "vid").limit(walkers)
    at = cut(starts.select(F.col("vid").alias("home"), F.col("vid").alias("here")))
    visited = at.select(F.col("here").alias("vid"))
    for step in range(steps):
        draw = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:{step}:"), F.col("home").cast("string")).cast("binary")), 1, 12), 16, 10).cast("long")
        known = at.withColumn("draw", draw).join(degree.withColumnRenamed("src", "here"), "here", "left")
        go = known.where(F.col("n").isNotNull() & (F.col("draw") % restart_in != 0)).withColumn("i", F.expr(f"cast((draw div {restart_in}) % n as int)"))
        moved = go.join(listed.select(F.col("src").alias("here"), "i", "dst"), ["here", "i"]).select("home", F.col("dst").alias("here"))
        back = known.where(F.col("n").isNull() | (F.col("draw") % restart_in == 0)).select("home", F.col("home").alias("here"))
        at = cut(moved.union(back))
        visited = visited.union(at.select("here"))
    seen = visited.distinct()
    return edges.select("src", "dst").join(seen.toDF("src"), "src", "left_semi").join(seen.toDF("dst"), "dst", "left_semi").distinct()


def scale_up(graph: Graph, copies: int) -> Graph:
    """``copies`` disjoint copies with renumbered ids."""
    top = graph.vertices.agg(F.max("vid")).first()[0] or 0
    n = graph.spark.range(copies).select(F.col("id").alias("copy"))
    shift = F.col("copy") * (top + 1)
    v = graph.vertices.select("vid").withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).select((F.col("vid") + shift).alias("vid"))
    e = graph.edges.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).select((F.col("src") + shift).alias("src"), (F.col("dst") + shift).alias("dst"), "weight")
    del n
    return Graph(v, e)


def graph_stats(graph: Graph) -> DataFrame:
    """vertices, edges, average and largest out-degree."""
    d = graph.vertices.join(graph.edges.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("d")), "vid", "left")
    d = d.select(F.coalesce("d", F.lit(0)).alias("d"))
    return d.agg(F.count("*").alias("vertices"), F.sum("d").cast("long").alias("edges"), F.round(F.sum("d") / F.count("*"), 6).alias("avg_degree"), F.max("d").cast("long").alias("max_degree"))


# ---------------------------------------------------------------- trees and lists


def euler_tour(tree: DataFrame, parent_first: bool = False) -> DataFrame:
    """``tree``(parent, child) -> successor of each arc in the circular tour: (src, dst, next_src, next_dst).

    The arc after (u, v) leaves v for the neighbour after u in v's order, around; ``parent_first`` puts the parent
    before the children in that order, so that children are visited by rising id.
    """
    down = tree.select(F.col("parent").alias("src"), F.col("child").alias("dst"), F.lit(1).alias("down"))
    arcs = down.union(tree.select("child", "parent", F.lit(0 if parent_first else 1)))
    order = Window.partitionBy("src").orderBy("down", "dst")
    ring = arcs.withColumn("after", F.coalesce(F.lead("dst").over(order), F.first("dst").over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))))
    turn = ring.select(F.col("src").alias("next_src"), F.col("dst").alias("came"), F.col("after").alias("next_dst"))
    return arcs.join(turn, (F.col("dst") == F.col("next_src")) & (F.col("src") == F.col("came"))).select("src", "dst", "next_src", "next_dst")


def list_rank(succ: DataFrame, most_rounds: int = 64) -> DataFrame:
    """``succ``(vid, next), next null at ends -> (vid, rank): how many elements follow; pointer doubling."""
    at = cut(succ.select("vid", "next", F.when(F.col("next").isNull(), 0).otherwise(1).cast("long").alias("rank")))
    for _ in range(most_rounds):
        jump = at.select(F.col("vid").alias("next"), F.col("next").alias("beyond"), F.col("rank").alias("more"))
        at = cut(at.join(jump, "next", "left").select("vid", F.col("beyond").alias("next"), (F.col("rank") + F.coalesce("more", F.lit(0))).alias("rank")))
        if not at.where("next IS NOT NULL").limit(1).count():
            return at.select("vid", "rank")
    raise RuntimeError("the list has a cycle")


def tree_order(tree: DataFrame, root: int) -> DataFrame:
    """(vid, pre, post, size, depth) from 1, children in id order: list ranking of the Euler tour, then running sums.

    Arcs are ranked in parallel; the running sums over ranks are dealt in ranges, with one offset a range.
    """
    arcs = cut(euler_tour(tree, parent_first=True))
    first = tree.where(F.col("parent") == root).agg(F.min("child")).first()[0]
    if first is None:
        return tree.sparkSession.createDataFrame([(root, 1, 1, 1, 0)], "vid long, pre long, post long, size long, depth long")
    name = lambda a, b: F.concat_ws(":", F.col(a).cast("string"), F.col(b).cast("string"))
    ends = (F.col("next_src") == root) & (F.col("next_dst") == first)
    ids = arcs.select(F.xxhash64(name("src", "dst")).alias("vid"), F.when(~ends, F.xxhash64(name("next_src", "next_dst"))).alias("next"), "src", "dst")
    n = ids.count()
    ranked = list_rank(ids.select("vid", "next")).join(ids, "vid").select("src", "dst", (F.lit(n - 1) - F.col("rank")).alias("at"))
    down = ranked.join(tree.select(F.col("parent").alias("src"), F.col("child").alias("dst")).withColumn("down", F.lit(1)), ["src", "dst"], "left")
    down = cut(down.withColumn("down", F.coalesce("down", F.lit(0))).withColumn("range", F.expr("at div 4096")))
    sums = down.groupBy("range").agg(F.sum("down").alias("d"), F.count("*").alias("n"))
    running = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select("range", F.coalesce(F.sum("d").over(running), F.lit(0)).alias("d0"), F.coalesce(F.sum("n").over(running), F.lit(0)).alias("n0"))
    inside = Window.partitionBy("range").orderBy("at").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    told = down.join(offsets, "range").withColumn("downs", F.col("d0") + F.sum("down").over(inside)).withColumn("ups", F.col("at") + 1 - F.col("downs"))
    fore = told.where("down = 1").select(F.col("dst").alias("vid"), (F.col("downs") + 1).alias("pre"), (F.col("downs") - F.col("ups")).alias("depth"), F.col("at").alias("a"))
    back = told.where("down = 0").select(F.col("src").alias("vid"), F.col("ups").alias("post"), F.col("at").alias("b"))
    rows = fore.join(back, "vid").select("vid", "pre", "post", F.expr("(b - a + 1) div 2").alias("size"), "depth")
    top = tree.sparkSession.createDataFrame([(root, 1, n // 2 + 1, n // 2 + 1, 0)], rows.schema)
    return rows.union(top)


def merge_paths(nodes: DataFrame, succ: DataFrame, most_rounds: int = 64) -> DataFrame:
    """``nodes``(vid, seq), ``succ``(vid, next) of unbranched chains -> (head, seq, length): one row a chain.

    Pointer doubling over numbers: each round a node that does not know its chain's last one looks twice as far.  Texts
    meet once, where a chain's nodes are put in order, so what is written and sent grows with the texts and not with
    the square of a chain.
    """
    links = succ.where("next IS NOT NULL").join(nodes.select(F.col("vid").alias("next")), "next", "left_semi")
    far = F.coalesce("next", "vid")
    at = cut(nodes.select("vid").join(links, "vid", "left").select("vid", far.alias("last"), F.when(F.col("next").isNull(), 0).otherwise(1).cast("long").alias("rank"), F.col("next").isNotNull().alias("open")))
    for _ in range(most_rounds):
        if not at.where("open").limit(1).count():
            break
        jump = at.select(F.col("vid").alias("last"), F.col("last").alias("beyond"), F.col("rank").alias("more"))
        moved = at.where("open").join(jump, "last").select("vid", F.col("beyond").alias("last"), (F.col("rank") + F.col("more")).alias("rank"), (F.col("more") > 0).alias("open"))
        at = cut(at.where("NOT open").union(moved))
    else:
        raise RuntimeError("a chain has a cycle")
    row = F.struct((-F.col("rank")).alias("at"), "vid", "seq")
    chains = at.select("vid", "last", "rank").join(nodes, "vid").groupBy("last").agg(F.array_sort(F.collect_list(row)).alias("path"))
    return chains.select(F.element_at("path", 1)["vid"].alias("head"), F.array_join(F.transform("path", lambda x: x["seq"]), " ").alias("seq"), F.size("path").cast("long").alias("length"))


# ---------------------------------------------------------------- components of other kinds


def min_label(pairs: DataFrame, nodes: DataFrame, most_rounds: int = 64) -> DataFrame:
    """(vid, label): smallest id of the component, by hooking and pointer jumping in O(log n) rounds."""
    both = cut(pairs.select("src", "dst").union(pairs.select("dst", "src")).toDF("src", "dst"))
    at = cut(nodes.select("vid", F.col("vid").alias("label")))
    for _ in range(most_rounds):
        lab = at.toDF("dst", "other")
        near = both.join(lab, "dst").groupBy(F.col("src").alias("vid")).agg(F.min("other").alias("near"))
        own = at.join(near, "vid", "left").select("vid", "label", F.least("label", F.coalesce("near", "label")).alias("low"))
        hook = own.groupBy(F.col("label").alias("vid")).agg(F.min("low").alias("low"))
        hooked = own.join(hook.toDF("label", "root_low"), "label").select("vid", "label", F.least("low", "root_low").alias("new"))
        jump = hooked.select(F.col("vid").alias("new"), F.col("new").alias("up"))
        nxt = cut(hooked.join(jump, "new").select("vid", "label", F.col("up").alias("new")))
        if not nxt.where("new <> label").limit(1).count():
            return nxt.select("vid", "label")
        at = nxt.select("vid", F.col("new").alias("label"))
    raise RuntimeError("labels did not settle")


def hash_to_min(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """(vid, label): smallest id of the component.  Each vertex keeps a set of ids, one row each; a round sends the set
    to its smallest id and the smallest id to the set, until no set changes.

    The smallest vertex of a component ends with a row for each of its members, in rows of their own.
    """
    both = pairs.select("src", "dst").union(pairs.select("dst", "src")).union(nodes.select("vid", "vid")).toDF("vid", "near")
    at = cut(both.distinct())
    while True:
        low = at.groupBy("vid").agg(F.min("near").alias("low"))
        told = at.join(low, "vid").select(F.explode(F.array(F.struct(F.col("low").alias("vid"), "near"), F.struct(F.col("near").alias("vid"), F.col("low").alias("near")))).alias("x"))
        nxt = cut(told.select("x.*").distinct())
        if nxt.count() == at.count() and not nxt.join(at, ["vid", "near"], "left_anti").limit(1).count():
            return nxt.groupBy("vid").agg(F.min("near").alias("label"))
        at = nxt


def biconnected(pairs: DataFrame, hints=None) -> dict[str, DataFrame]:
    """Blocks of an undirected graph: ``edges``(src, dst, block), ``articulation``(vid), ``bridges``(src, dst).

    Per component: BFS tree, orders, low and high of each subtree over non-tree edges; tree edges of one block are
    linked in an auxiliary graph whose components are the blocks.  A block's name is its smallest edge child.
    """
    e = cut(pairs.select(F.least("src", "dst").alias("u"), F.greatest("src", "dst").alias("v")).where("u <> v").distinct())
    both = e.union(e.select("v", "u")).toDF("src", "dst")
    nodes = both.select(F.col("src").alias("vid")).distinct()
    labels = min_label(e.toDF("src", "dst"), nodes)
    # one tree for the forest: a super root above the smallest vertex of each component
    tree = cut(_bfs_forest(both, labels.select("label").distinct().toDF("root")))
    top = -1
    whole = tree.select(F.when(F.col("parent") == F.col("vid"), F.lit(top)).otherwise(F.col("parent")).cast("long").alias("parent"), F.col("vid").alias("child"))
    order = cut(tree_order(whole, top))
    pre = order.select("vid", "pre", "size")
    par = whole.select(F.col("child").alias("vid"), "parent")
    tree_edges = par.where(f"parent <> {top}").select(F.least("vid", "parent").alias("u"), F.greatest("vid", "parent").alias("v"))
    other = e.join(tree_edges, ["u", "v"], "left_anti")
    reach = other.union(other.select("v", "u")).toDF("vid", "far").join(pre.select(F.col("vid").alias("far"), F.col("pre").alias("p")), "far")
    own = reach.groupBy("vid").agg(F.min("p").alias("lo"), F.max("p").alias("hi"))
    own = cut(pre.join(own, "vid", "left").select("vid", "pre", "size", F.least("pre", F.coalesce("lo", "pre")).alias("lo"), F.greatest("pre", F.coalesce("hi", "pre")).alias("hi")))
    sub = cut(_subtree_extremes(own, par))
    info = sub.join(par, "vid").join(pre.select(F.col("vid").alias("parent"), F.col("pre").alias("ppre"), F.col("size").alias("psize")), "parent", "left").where(f"parent <> {top}")
    info = cut(info.select("vid", "parent", "pre", "size", "lo", "hi", "ppre", "psize"))
    # a child's edge is in its parent's block if the child's subtree reaches outside the parent's subtree
    up = info.where("lo < ppre OR hi >= ppre + psize").join(info.select(F.col("vid").alias("parent")), "parent", "left_semi").select(F.col("vid").alias("src"), F.col("parent").alias("dst"))
    # a non-tree edge between unrelated vertices ties the two edges above its ends
    span = pre.toDF("u", "pu", "su")
    cross = other.join(span, "u").join(pre.toDF("v", "pv", "sv"), "v").where("NOT (pv >= pu AND pv < pu + su) AND NOT (pu >= pv AND pu < pv + sv)").select(F.col("u").alias("src"), F.col("v").alias("dst"))
    blocks = min_label(up.union(cross), info.select("vid"))
    deeper = e.join(pre.select(F.col("vid").alias("u"), F.col("pre").alias("pu")), "u").join(pre.select(F.col("vid").alias("v"), F.col("pre").alias("pv")), "v")
    named = deeper.withColumn("vid", F.when(F.col("pu") > F.col("pv"), F.col("u")).otherwise(F.col("v"))).join(blocks, "vid").select(F.col("u").alias("src"), F.col("v").alias("dst"), F.col("label").alias("block"))
    named = cut(named)
    ends = named.select("block", F.explode(F.array("src", "dst")).alias("vid")).distinct()
    return {
        "edges": named,
        "articulation": ends.groupBy("vid").agg(F.count("*").alias("n")).where("n > 1").select("vid"),
        "bridges": named.groupBy("block").agg(F.count("*").alias("n"), F.min("src").alias("src"), F.min("dst").alias("dst")).where("n = 1").select("src", "dst"),
    }


def _bfs_forest(both: DataFrame, roots: DataFrame) -> DataFrame:
    """(vid, parent) of breadth-first trees from all roots at once; a root is its own parent."""
    done = cut(roots.select(F.col("root").alias("vid"), F.col("root").alias("parent")))
    edge = done
    while True:
        found = edge.select(F.col("vid").alias("src")).join(both, "src").groupBy(F.col("dst").alias("vid")).agg(F.min("src").alias("parent"))
        edge = cut(found.join(done, "vid", "left_anti"))
        if not edge.limit(1).count():
            return done
        done = cut(done.union(edge))


def _subtree_extremes(own: DataFrame, par: DataFrame) -> DataFrame:
    """lo and hi over each subtree, in O(log depth) rounds of doubling along ancestors."""
    # each round a vertex passes what it has to its ancestor 2**i up, which by then holds all nearer descendants
    at = own
    up = par.select("vid", F.col("parent").alias("anc"))
    while True:
        up = cut(up.where("anc >= 0"))
        if not up.limit(1).count():
            return at
        given = at.select("vid", "lo", "hi").join(up, "vid").groupBy(F.col("anc").alias("vid")).agg(F.min("lo").alias("l"), F.max("hi").alias("h"))
        at = cut(at.join(given, "vid", "left").select("vid", "pre", "size", F.least("lo", F.coalesce("l", "lo")).alias("lo"), F.greatest("hi", F.coalesce("h", "hi")).alias("hi")))
        up = up.join(up.select(F.col("vid").alias("anc"), F.col("anc").alias("beyond")), "anc").select("vid", F.col("beyond").alias("anc"))


def scc(graph: Graph) -> DataFrame:
    """(vid, label): strongly connected components named by their largest vertex.

    Rounds of trimming what has no in- or out-edge, colouring forwards by the largest id that reaches a vertex, and
    walking backwards from each colour's own vertex inside its colour; what is reached is a component and goes.  Each
    round finds one component at least, and rounds go on until no vertex is left.
    """
    v, e = cut(graph.vertices.select("vid")), cut(graph.edges.select("src", "dst").where("src <> dst").distinct())
    done = []
    while True:
        for _ in range(2):  # trimming only spares later work, so a few passes a round will do
            alone = cut(v.join(e.select(F.col("src").alias("vid")), "vid", "left_anti").union(v.join(e.select(F.col("dst").alias("vid")), "vid", "left_anti")).distinct())
            if not alone.limit(1).count():
                break
            done.append(alone.select("vid", F.col("vid").alias("label")))
            v = cut(v.join(alone, "vid", "left_anti"))
            e = cut(e.join(alone.toDF("src"), "src", "left_anti").join(alone.toDF("dst"), "dst", "left_anti"))
        if not v.limit(1).count():
            break
        colour = cut(v.select("vid", F.col("vid").alias("colour")))
        while True:
            rows = colour.withColumn("before", F.col("colour"))
            for _ in range(HOPS):
                got = e.join(rows.select(F.col("vid").alias("src"), F.col("colour").alias("c")), "src").groupBy(F.col("dst").alias("vid")).agg(F.max("c").alias("c"))
                rows = rows.join(got, "vid", "left").select("vid", F.greatest("colour", F.coalesce("c", "colour")).alias("colour"), "before")
            rows = cut(rows)
            colour = rows.select("vid", "colour")
            if not rows.where("colour > before").limit(1).count():
                break
        same = e.join(colour.toDF("src", "cs"), "src").join(colour.toDF("dst", "cd"), "dst").where("cs = cd").select("src", "dst")
        same = cut(same)
        front = hit = cut(colour.where("vid = colour").select("vid"))
        while True:
            grown = front
            for _ in range(HOPS):
                grown = grown.union(grown.toDF("dst").join(same, "dst").select(F.col("src").alias("vid"))).distinct()
            front = cut(grown.join(hit, "vid", "left_anti"))
            if not front.limit(1).count():
                break
            hit = cut(hit.union(front))
        done.append(colour.join(hit, "vid").select("vid", F.col("colour").alias("label")))
        v = cut(v.join(hit, "vid", "left_anti"))
        e = cut(e.join(hit.toDF("src"), "src", "left_anti").join(hit.toDF("dst"), "dst", "left_anti"))
    out = done[0] if done else v.select("vid", F.col("vid").alias("label"))
    for d in done[1:]:
        out = out.union(d)
    return out


def transitive_closure(edges: DataFrame, most_length: int | None = None, semi_naive: bool = True) -> DataFrame:
    """(src, dst, hops): shortest number of edges, up to ``most_length`` if given; only new pairs are extended if semi-naive."""
    e = cut(edges.select("src", "dst").distinct())
    known = cut(e.withColumn("hops", F.lit(1).cast("long")))
    front = known
    for n in count(2) if most_length is None else range(2, most_length + 1):
        longer = front if semi_naive else known
        grown = longer.select("src", F.col("dst").alias("mid")).join(e.toDF("mid", "dst"), "mid").select("src", "dst").distinct()
        front = cut(grown.join(known, ["src", "dst"], "left_anti").withColumn("hops", F.lit(n).cast("long")))
        if not front.limit(1).count():
            break
        known = cut(known.union(front))
    return known
