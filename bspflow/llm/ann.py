"""Approximate nearest neighbours by inner product: a forest of random-projection trees and exact reranking.

Trees split a bounded sample (``sample`` vectors, the first in the order of a hash of their ids) at the median of
its projections on the difference of two sample points; inner product becomes nearness by one more coordinate
that lifts every vector to the largest norm.  Every vector is indexed in every tree.  A query searches all trees
through one shared priority queue: the entry whose worst margin on its way down is best is opened next, until
the leaves it opened hold, repeats in several trees counted, the share of the index it asks for.  That share is the least of ``SHARES`` at which sample vectors find
``recall`` of their nearest among the sample.

Leaves are dealt out in blocks of at most ``block`` rows and of ``block`` queries, so a leaf that holds a third of
all vectors is many blocks.  A block of queries meets a block of vectors in one matrix product; what may be among the
nearest is scored again one by one in double precision, in the same order of addition wherever the row lies, so
copies tie exactly.  A query only sends on candidates that reach the score of its k-th best sample vector among the
leaves it searches: there are at least k candidates above that, so none of its nearest are lost.

Defined cases: null or empty vectors, vectors with null, NaN or infinite components, zero vectors, null ids and
vectors of another length than most are left out; rows that repeat an id count once (the smallest vector); with
fewer candidates than k all are returned; empty tables give empty results; extra columns are ignored.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize, plain

SHARES = (0.02, 0.05, 0.1, 0.2, 0.3, 0.45, 0.6, 0.8, 1.0, 1.3, 1.6, 2.0)
SLACK = 1e-9


def usable(vectors: DataFrame, vector: str = "embedding", zero: bool = False) -> DataFrame:
    """(vec_id, v as array<double>): one row an id, without those that the docstring leaves out."""
    v = F.col(vector).cast("array<double>")
    bad = F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    kept = plain(vectors, "vec_id", vector).select("vec_id", v.alias("v")).where("vec_id IS NOT NULL AND v IS NOT NULL AND size(v) > 0").where(~bad)
    if not zero:
        kept = kept.where(F.exists("v", lambda x: x != 0))
    usual = kept.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").limit(1).select("n").first()
    if usual:
        kept = kept.where(F.size("v") == usual.n)
    return kept.groupBy("vec_id").agg(F.min("v").alias("v"))


class Forest:
    """Trees over lifted vectors, as arrays: inner nodes first, children by number, leaves numbered in each tree."""

    def __init__(self, points: np.ndarray, top: float, trees: int, leaves: int, seed: int):
        self.top = top
        lifted = self.lift(points)
        self.trees = [self._grow(lifted, leaves, np.random.default_rng([seed, t])) for t in range(trees)]

    def lift(self, x: np.ndarray) -> np.ndarray:
        rest = np.sqrt(np.maximum(self.top**2 - (x * x).sum(1), 0))
        return np.column_stack((x, rest)).astype(np.float32)

    def _grow(self, x: np.ndarray, leaves: int, rng: np.random.Generator) -> dict:
        normals, cuts, kids, n_leaves = [], [], [], 0
        root: list = [None]
        todo = [(np.arange(len(x)), leaves, None, 0)]
        while todo:
            rows, want, parent, side = todo.pop()
            node = None
            if want > 1 and len(rows) > 8:
                for _ in range(3):
                    a, b = rng.choice(len(rows), 2, replace=False)
                    normal = x[rows[a]] - x[rows[b]]
                    size = np.linalg.norm(normal)
                    if size < 1e-6:
                        continue
                    normal = normal / size
                    p = x[rows] @ normal
                    cut = np.median(p)
                    right = p > cut
                    if 0 < right.sum() < len(rows):
                        node = len(normals)
                        normals.append(normal)
                        cuts.append(cut)
                        kids.append([0, 0])
                        todo.append((rows[right], want // 2, node, 1))
                        todo.append((rows[~right], want - want // 2, node, 0))
                        break
            here = node if node is not None else -1 - n_leaves
            n_leaves += node is None
            if parent is None:
                root[0] = here
            else:
                kids[parent][side] = here
        width = x.shape[1]
        return {"root": root[0], "normals": np.array(normals, np.float32).reshape(-1, width), "cuts": np.array(cuts, np.float32), "kids": np.array(kids, np.int64).reshape(-1, 2), "leaves": n_leaves}

    def leaf_of(self, x: np.ndarray) -> np.ndarray:
        """Leaf of each vector in each tree, (rows, trees)."""
        y, out = self.lift(x), np.zeros((len(x), len(self.trees)), np.int32)
        for t, tree in enumerate(self.trees):
            at = np.full(len(x), tree["root"])
            while True:
                inner = np.flatnonzero(at >= 0)
                if not len(inner):
                    break
                n = at[inner]
                right = (y[inner] * tree["normals"][n]).sum(1) > tree["cuts"][n]
                at[inner] = tree["kids"][n, right.astype(np.int64)]
            out[:, t] = -1 - at
        return out

    def search(self, queries: np.ndarray, sizes: list[np.ndarray], want: float) -> list[list[tuple[int, int]]]:
        """For each query the (tree, leaf) opened by one queue over all trees, until their sizes reach ``want``."""
        y = np.column_stack((queries, np.zeros(len(queries)))).astype(np.float32)
        y /= np.maximum(np.linalg.norm(y, axis=1, keepdims=True), 1e-30)
        y *= self.top
        margins = [(y @ t["normals"].T - t["cuts"]).tolist() for t in self.trees]
        found = []
        for q in range(len(queries)):
            queue = [(-np.inf, t, tree["root"]) for t, tree in enumerate(self.trees)]
            heapq.heapify(queue)
            got, leaves = 0, []
            while queue and got < want:
                worst, t, node = heapq.heappop(queue)
                if node < 0:
                    leaves.append((t, -1 - node))
                    got += sizes[t][-1 - node]
                    continue
                m = margins[t][q][node]
                low, high = self.trees[t]["kids"][node].tolist()
                heapq.heappush(queue, (max(worst, m), t, low))
                heapq.heappush(queue, (max(worst, -m), t, high))
            found.append(leaves)
        return found


def _exact(q: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Inner products row by row; each is added up in an order that only depends on the length."""
    return (q * v).sum(axis=1)


def _calibrate(forest: Forest, points: np.ndarray, k: int, recall: float, tries: int = 200) -> float:
    """The least share of the index at which sample vectors find ``recall`` of their k nearest in the sample."""
    n = len(points)
    k = min(k, n - 1)
    if k < 1:
        return float(len(forest.trees))
    asked = np.linspace(0, n - 1, min(tries, n)).astype(np.int64)
    scores = points[asked] @ points.T
    scores[np.arange(len(asked)), asked] = -np.inf
    true = np.argpartition(-scores, k - 1, axis=1)[:, :k]
    leaf = forest.leaf_of(points)
    sizes = [np.bincount(leaf[:, t], minlength=tree["leaves"]) for t, tree in enumerate(forest.trees)]
    for share in (x for x in SHARES if x < len(forest.trees)):
        hit = 0
        for i, leaves in enumerate(forest.search(points[asked], sizes, share * n)):
            open_ = [np.zeros(tree["leaves"], bool) for tree in forest.trees]
            for t, x in leaves:
                open_[t][x] = True
            reached = np.zeros(k, bool)
            for t in range(len(forest.trees)):
                reached |= open_[t][leaf[true[i], t]]
            hit += reached.sum()
        if hit >= recall * k * len(asked):
            return share
    return float(len(forest.trees))


def _matrix(arrow: pa.ListArray, width: int) -> np.ndarray:
    return arrow.flatten().to_numpy(zero_copy_only=False).reshape(-1, width)


def _leaf_rows(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forest, width = shared.value["forest"], shared.value["width"]
        for batch in batches:
            if batch.num_rows:
                x = _matrix(batch.column("v"), width)
                leaf = forest.leaf_of(x)
                yield pa.RecordBatch.from_arrays([batch.column("vec_id"), batch.column("v"), pa.array(list(leaf), pa.list_(pa.int32()))], names=["vec_id", "v", "leaf"])

    return run


def _probe_rows(shared, k: int):
    """Queries -> (query_id, v, floor, tree, leaf) for each leaf they open."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = shared.value
        forest, width, points, ids, home = s["forest"], s["width"], s["points"], s["ids"], s["home"]
        for whole in batches:
            for start in range(0, whole.num_rows, 256):
                batch = whole.slice(start, 256)
                x = _matrix(batch.column("v"), width)
                own = batch.column("vec_id").to_numpy(zero_copy_only=False)
                scores = x @ points.T
                query, tree, leaf, floor = [], [], [], []
                for i, leaves in enumerate(forest.search(x, s["sizes"], s["want"])):
                    open_ = [np.zeros(t["leaves"], bool) for t in forest.trees]
                    for t, n in leaves:
                        open_[t][n] = True
                    seen = np.zeros(len(points), bool)
                    for t in range(len(forest.trees)):
                        seen |= open_[t][home[:, t]]
                    seen &= ids != own[i]
                    got = scores[i][seen]
                    floor += [float(np.partition(got, len(got) - k)[len(got) - k]) - SLACK if len(got) >= k else -np.inf] * len(leaves)
                    query += [i] * len(leaves)
                    tree += [t for t, _ in leaves]
                    leaf += [n for _, n in leaves]
                at = pa.array(query, pa.int64())
                yield pa.RecordBatch.from_arrays([batch.column("vec_id").take(at), batch.column("v").take(at), pa.array(floor, pa.float64()), pa.array(tree, pa.int32()), pa.array(leaf, pa.int32())], names=["query_id", "v", "floor", "tree", "leaf"])

    return run


def _rerank_rows(k: int, width: int):
    """A block of vectors and a block of queries -> (query_id, vec_id, score), at most k a query and ties."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1)
                members, asked = row.column("members").flatten(), row.column("asked").flatten()
                v, ids = _matrix(members.field("v"), width), members.field("vec_id").to_numpy(zero_copy_only=False)
                q, own = _matrix(asked.field("v"), width), asked.field("query_id").to_numpy(zero_copy_only=False)
                floor = asked.field("floor").to_numpy(zero_copy_only=False)
                rough = q @ v.T
                rough[own[:, None] == ids[None, :]] = -np.inf
                if len(ids) > k:
                    floor = np.maximum(floor, np.partition(rough, len(ids) - k, axis=1)[:, len(ids) - k] - SLACK)
                a, b = np.nonzero((rough >= floor[:, None]) & (rough > -np.inf))
                if not len(a):
                    continue
                score = _exact(q[a], v[b])
                order = np.lexsort((ids[b], -score, a))
                a, b, score = a[order], b[order], score[order]
                rank = np.arange(len(a)) - np.searchsorted(a, a)
                keep = rank < k
                yield pa.RecordBatch.from_arrays([pa.array(own[a[keep]]), pa.array(ids[b[keep]]), pa.array(score[keep])], names=["query_id", "vec_id", "score"])

    return run


def _blocks(rows: DataFrame, keys: list[str], count: Column, item: Column, name: str) -> DataFrame:
    """Rows of a key gathered in ``count`` blocks of about even size."""
    return rows.withColumn(f"{name}_block", F.pmod(F.xxhash64("part_key"), count)).groupBy(*keys, f"{name}_block").agg(F.collect_list(item).alias(name))


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 20, trees: int = 4, leaf_rows: int = 256, most_leaves: int = 1024, sample: int = 16384, recall: float = 0.95, block: int = 2048, seed: int = 7, vector: str = "embedding") -> DataFrame:
    """The k nearest of ``vectors`` found for each of ``queries`` (both with vec_id and the vector column).

    Returns query_id, rank (from 1), vec_id, score; ties go to the smaller vec_id.  ``sample`` bounds what the
    trees are fitted on; ``most_leaves`` bounds what is broadcast.
    """
    spark = vectors.sparkSession
    base = materialize(usable(vectors, vector), "vectors")
    asked = usable(queries, vector) if queries is not vectors else base
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    told = base.agg(F.count("*").alias("n"), F.max(F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))).alias("top"), F.max(F.size("v")).alias("width")).first()
    if not told.n:
        return empty
    fitted = base.orderBy(F.xxhash64("vec_id", F.lit(seed)), "vec_id").limit(sample).toPandas()
    points, ids = np.array(fitted["v"].tolist(), np.float64), fitted["vec_id"].to_numpy(np.int64)
    # small tables have leaves of 16 rows and more, so that the forest does its work at every size
    leaves = int(min(most_leaves, max(told.n // leaf_rows, 8), max(1, len(points) // 16)))
    forest = Forest(points, told.top, trees, leaves, seed)
    share = _calibrate(forest, points, k, recall)
    parts = {"forest": forest, "width": told.width, "points": points, "ids": ids, "home": forest.leaf_of(points)}
    shared = spark.sparkContext.broadcast(parts)
    indexed = materialize(base.mapInArrow(_leaf_rows(shared), "vec_id long, v array<double>, leaf array<int>").select("vec_id", "v", F.posexplode("leaf").alias("tree", "leaf")), "leaves")
    counts = indexed.groupBy("tree", "leaf").count()
    sizes = [np.zeros(t["leaves"], np.int64) for t in forest.trees]
    for row in counts.toLocalIterator():
        sizes[row.tree][row.leaf] = row["count"]
    parts = parts | {"sizes": sizes, "want": share * told.n}
    searching = spark.sparkContext.broadcast(parts)
    probes = materialize(asked.where(F.size("v") == told.width).mapInArrow(_probe_rows(searching, k), "query_id long, v array<double>, floor double, tree int, leaf int"), "probes")
    held = counts.select("tree", "leaf", F.ceil(F.col("count") / block).cast("int").alias("m_blocks"))
    wanted = probes.groupBy("tree", "leaf").agg(F.ceil(F.count("*") / block).cast("int").alias("q_blocks"))
    members = _blocks(indexed.withColumn("part_key", F.col("vec_id")).join(held.join(wanted, ["tree", "leaf"]), ["tree", "leaf"]), ["tree", "leaf", "m_blocks", "q_blocks"], F.col("m_blocks"), F.struct("vec_id", "v"), "members")
    members = members.withColumn("q_block", F.explode(F.sequence(F.lit(0), F.col("q_blocks") - 1)))
    asking = _blocks(probes.withColumn("part_key", F.col("query_id")).join(held.join(wanted, ["tree", "leaf"]), ["tree", "leaf"]), ["tree", "leaf", "m_blocks", "q_blocks"], F.col("q_blocks"), F.struct("query_id", "v", "floor"), "asked")
    asking = asking.withColumn("m_block", F.explode(F.sequence(F.lit(0), F.col("m_blocks") - 1))).select("tree", "leaf", F.col("asked_block").cast("int").alias("q_block"), "m_block", "asked")
    members = members.select("tree", "leaf", "q_block", F.col("members_block").cast("int").alias("m_block"), "members")
    met = members.join(asking, ["tree", "leaf", "q_block", "m_block"]).select("members", "asked")
    scored = met.mapInArrow(_rerank_rows(k, told.width), "query_id long, vec_id long, score double")
    return top_k(scored.groupBy("query_id", "vec_id").agg(F.max("score").alias("score")), k)


def top_k(scored: DataFrame, k: int) -> DataFrame:
    """(query_id, vec_id, score) -> the k best of each query with their rank."""
    from pyspark.sql import Window

    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def exact_nearest(vectors: DataFrame, queries: DataFrame, k: int = 20, vector: str = "embedding") -> DataFrame:
    """Brute force for measuring recall on small tables: every query against every vector, in one join."""
    base, asked = usable(vectors, vector), usable(queries, vector).select(F.col("vec_id").alias("query_id"), F.col("v").alias("q"))
    dot = F.aggregate(F.zip_with("q", "v", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    return top_k(asked.join(base, F.col("query_id") != F.col("vec_id")).select("query_id", "vec_id", dot.alias("score")), k)
