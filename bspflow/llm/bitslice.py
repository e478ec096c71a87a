"""Exact top-k by inner product of quantised vectors over a bit-sliced index.

Every component becomes floor(scale * x), as a whole number.  A block of at most ``block`` rows keeps, for each
component, one bitmap a bit of its value above the component's least value in the block.  A query's score is a sum
of slices: each signed digit of a query component adds the component's slices at the digit's weight, complemented
for a negative digit (the constants this leaves are the same for all rows).  Full adders of bitmap operations fold
the slices of equal weight until one slice of each weight is left, the slices of the score.  The top rows come from
a walk from the most significant slice down: rows with the bit set are surely in if they are at most k, else they
are the only ones left; rows still equal at the end are the boundary, resolved by the smaller vec_id.

Queries are a stated set and meet the index in tiles: a block of rows and a set of queries.  A tile's work grows with both
sides and its bytes with one, so sets are as large as ``query_block`` where blocks alone keep the cluster busy: an
index block then moves once for that many queries (some 5 MB for ten seconds of work), and a set once for each block.
Where blocks are few, sets are smaller, so that no task has all the work.  A tile sends k rows a query, which a window
ranks.  Nothing depends on how values repeat.

Defined cases: null or empty vectors, vectors with null, NaN or infinite components, null ids and vectors of
another length than most are left out; components are whole longs of any size, and scores that might not fit a long
raise before any is computed; rows that repeat an id count once (the smallest vector); fewer candidates than k all are
returned; empty tables give empty results; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .ann import top_k, usable
from .common import materialize

#: Largest size of a vector, and of a product of two, that whole longs hold with a margin for the index's sums.
MOST = float(1 << 62)


def quantise(scale: float):
    """floor(scale * x) as a whole number; ``check_range`` tells whether all fit."""
    return lambda x: F.floor(x * scale).cast("long")


def check_range(longest: float | None, asked: float | None) -> None:
    """Raise unless components and all inner products of vectors of these lengths fit a long."""
    if longest is not None and (longest >= MOST or longest * (asked or 0.0) >= MOST):
        raise OverflowError(f"vectors of length {longest:.3g} and {asked or 0.0:.3g} have inner products beyond a long; take a smaller scale")


class Block:
    """A bit-sliced index of some rows: ``rows`` (n, width) whole numbers, by ascending id."""

    def __init__(self, ids: np.ndarray, low: np.ndarray, bits: np.ndarray, packed: np.ndarray):
        self.ids, self.low, self.n, self.width = ids, low, len(ids), len(low)
        self.words = -(-self.n // 64)
        self.bits = bits.tolist()
        self.every = self._pack(np.ones(self.n, bool))
        each = iter(packed.reshape(-1, self.words))
        self.slices = [[next(each) for _ in range(b)] for b in self.bits]
        self.inverse = [[s ^ self.every for s in of] for of in self.slices]

    @staticmethod
    def build(ids: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Sorted ids, least value and number of bits of each component, and the slices one after another."""
        order = np.argsort(ids, kind="stable")
        ids, rows = ids[order], rows[order].astype(np.int64)
        low = rows.min(0)
        up = rows - low
        bits = np.array([int(x).bit_length() for x in up.max(0)], np.int64)
        padded = np.zeros((int(bits.sum()), -(-len(ids) // 64) * 64), bool)
        at = 0
        for d, many in enumerate(bits.tolist()):
            for b in range(many):
                padded[at, : len(ids)] = (up[:, d] >> b) & 1
                at += 1
        return ids, low, bits, np.packbits(padded, axis=1, bitorder="little").view(np.uint64)

    def _pack(self, mask: np.ndarray) -> np.ndarray:
        bits = np.zeros(self.words * 64, bool)
        bits[: self.n] = mask
        return np.packbits(bits, bitorder="little").view(np.uint64)

    def _fold(self, weights: dict[int, list[np.ndarray]]) -> list[tuple[int, np.ndarray]]:
        """Full adders until one bitmap of each weight is left; (weight, bitmap) by rising weight."""
        out, w = [], min(weights, default=0)
        xor, and_, or_ = np.bitwise_xor, np.bitwise_and, np.bitwise_or
        while w <= max(weights, default=-1):
            here = weights.get(w, [])
            if here:
                up = weights.setdefault(w + 1, [])
                while len(here) > 2:
                    a, b, c = here.pop(), here.pop(), here.pop()
                    x = xor(a, b)
                    here.insert(0, xor(x, c))
                    and_(x, c, out=x)
                    carry = and_(a, b)
                    or_(carry, x, out=carry)
                    up.append(carry)
                if len(here) == 2:
                    a, b = here
                    up.append(and_(a, b))
                    here = [xor(a, b)]
                out.append((w, here[0]))
                if not up:
                    del weights[w + 1]
            w += 1
        return out

    def scores(self, query: np.ndarray) -> tuple[int, list[tuple[int, np.ndarray]]]:
        """A constant, and the slices of what each row's score is above it."""
        weights: dict[int, list[np.ndarray]] = {}
        constant = 0
        for d, q in enumerate(query.tolist()):
            if not q:
                continue
            constant += q * int(self.low[d])
            m = self.bits[d]
            for place, digit in signed_digits(q):
                of = self.slices[d] if digit > 0 else self.inverse[d]
                if digit < 0:
                    constant -= ((1 << m) - 1) << place
                for b in range(m):
                    weights.setdefault(place + b, []).append(of[b])
        return constant, self._fold(weights)

    def top(self, query: np.ndarray, k: int, leave: int | None) -> tuple[np.ndarray, np.ndarray]:
        """Ids and scores of the k best rows but ``leave``'s, ties to the smaller id; in no order."""
        constant, slices = self.scores(query)
        maybe = self.every
        at = np.searchsorted(self.ids, leave) if leave is not None else self.n
        if at < self.n and self.ids[at] == leave:
            maybe = maybe.copy()
            maybe[at >> 6] &= ~np.uint64(1 << (int(at) & 63))
        sure, n_sure = np.zeros_like(maybe), 0
        for _, s in reversed(slices):
            both = maybe & s
            n = n_sure + int(np.bitwise_count(both).sum())
            if n > k:
                maybe = both
                continue
            sure, n_sure = sure | both, n
            maybe = maybe & ~s
            if n == k:
                maybe = np.zeros_like(maybe)
                break
        rows = self._rows(sure)
        rows = np.concatenate((rows, self._rows(maybe)[: k - n_sure]))
        # sums may pass a long's range on the way; modulo 2**64 they come out right, as the score itself fits
        total = np.full(len(rows), constant & (1 << 64) - 1, np.uint64)
        shift = (rows & 63).astype(np.uint64)
        for w, s in slices:
            if w < 64:
                total += ((s[rows >> 6] >> shift) & np.uint64(1)) << np.uint64(w)
        return self.ids[rows], total.view(np.int64)

    def _rows(self, bitmap: np.ndarray) -> np.ndarray:
        some = np.flatnonzero(bitmap)
        inside = np.unpackbits(bitmap[some].view(np.uint8), bitorder="little").reshape(-1, 64)
        word, bit = np.nonzero(inside)
        return (some[word] << 6) + bit


def signed_digits(q: int) -> list[tuple[int, int]]:
    """The non-adjacent form of a whole number: (place, 1 or -1), the fewest digits that add up to it."""
    out, place = [], 0
    while q:
        if q & 1:
            digit = 2 - (q & 3)
            out.append((place, digit))
            q -= digit
        q >>= 1
        place += 1
    return out


#: Most partitions that tiles are dealt to.
MOST_PARTITIONS = 20_000
_PARTS = ("ids", "low", "bits", "slices")


def _index_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i in range(batch.num_rows):
            members = batch.column("members")[i].values
            ids = members.field("vec_id").to_numpy(zero_copy_only=False)
            made = Block.build(ids, members.field("z").flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1))
            yield pa.RecordBatch.from_arrays([batch.column("block").slice(i, 1), *[pa.array([x.tobytes()], pa.binary()) for x in made]], names=["block", *_PARTS])


def _search_rows(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                ids, low, bits = (np.frombuffer(batch.column(x)[i].as_buffer(), np.int64) for x in _PARTS[:3])
                block = Block(ids, low, bits, np.frombuffer(batch.column("slices")[i].as_buffer(), np.uint64))
                asked = batch.column("asked")[i].values
                own = asked.field("query_id").to_numpy(zero_copy_only=False)
                q = asked.field("z").flatten().to_numpy(zero_copy_only=False).reshape(len(own), -1)
                query, vec, score = [], [], []
                for one, z in zip(own.tolist(), q, strict=True):
                    got, total = block.top(z, k, one)
                    query.append(np.full(len(got), one))
                    vec.append(got)
                    score.append(total)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x).astype(np.int64)) for x in (query, vec, score)], names=["query_id", "vec_id", "score"])

    return run


def build_index(base: DataFrame, rows: int, block: int = 1 << 16) -> DataFrame:
    """``base``(vec_id, z) of ``rows`` rows -> one row a block: its ids, least values, bit counts and slices."""
    blocks = max(1, -(-rows // block))
    dealt = base.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    return dealt.groupBy("block").agg(F.collect_list(F.struct("vec_id", "z")).alias("members")).mapInArrow(_index_rows, "block int, ids binary, low binary, bits binary, slices binary")


def exact_top_k(vectors: DataFrame, queries: DataFrame, k: int = 20, scale: float = 64.0, block: int = 1 << 16, query_block: int = 4096, vector: str = "embedding") -> DataFrame:
    """The k best of ``vectors`` for each of ``queries`` by inner product of quantised components.

    Returns query_id, rank (from 1), vec_id, score.
    """
    spark = vectors.sparkSession
    length = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + F.floor(x * scale).cast("double") * F.floor(x * scale).cast("double"))).alias("length")
    whole = lambda df: usable(df, vector, zero=True).select("vec_id", F.transform("v", quantise(scale)).alias("z"), length)
    base = materialize(whole(vectors), "quantised")
    told = base.agg(F.count("*").alias("n"), F.max(F.size("z")).alias("width"), F.max("length").alias("longest")).first()
    if not told.n:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    asked = (base.join(queries.select("vec_id").distinct(), "vec_id", "left_semi") if queries is not vectors else base).where(F.size("z") == told.width)
    asked = materialize(asked.withColumnRenamed("vec_id", "query_id"), "asked")
    n = asked.agg(F.count("*").alias("asked"), F.max("length").alias("longest")).first()
    check_range(told.longest, n.longest)
    blocks = max(1, -(-told.n // block))
    busy = 4 * spark.sparkContext.defaultParallelism
    q_blocks = max(1, -(-n.asked // query_block), min(-(-busy // blocks), -(-n.asked // 64)))
    index = materialize(build_index(base, told.n, block), "index")
    sets = asked.withColumn("q_block", F.pmod(F.xxhash64("query_id"), F.lit(q_blocks)).cast("int")).groupBy("q_block").agg(F.collect_list(F.struct("query_id", "z")).alias("asked"))
    tiles = min(blocks * q_blocks, MOST_PARTITIONS)
    dealt = index.withColumn("q_block", F.explode(F.sequence(F.lit(0), F.lit(q_blocks - 1)))).repartition(tiles, "block", "q_block")
    asking = sets.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).repartition(tiles, "block", "q_block")
    met = dealt.join(asking.hint("shuffle_hash"), ["block", "q_block"]).select(*_PARTS, "asked")
    scored = met.mapInArrow(_search_rows(k), "query_id long, vec_id long, score long")
    return top_k(scored, k)
