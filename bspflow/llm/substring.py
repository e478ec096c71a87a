"""Substring deduplication by Rabin-Karp hashes of every fixed-length word window.

Pass 1 hashes every window of every text, folds repeats among some 260,000 of them, and counts in Spark in how many
documents a hash starts (its smallest and largest ``doc_id``).  Hashes of two or more documents are the repeated ones.
A bit filter of fixed size over them lets pass 2 look only at windows that may repeat, now under two independent
hashes of 64 bits: the smallest ``doc_id`` of each pair of hashes is the window's first document, and a join by the
pair flags the windows of later ones.  Flags travel as bits, 64 window starts a long, so rows that repeat add nothing;
flagged windows of a document merge into maximal removal intervals.

Cost: one row of 16 bytes a window in the first shuffle; one row a repeated window, twice, after that; one shuffle of
the texts; the texts are hashed three times, which costs less than to keep 128 bits of every window on disk.  The filter
has ``filter_bits`` bits whatever the input is; beyond some 10**8 repeated windows it fills up, more windows take part
in the second step, and the result stays the same.  No group of windows is ever gathered: repeats fold before the
shuffle, and the join of hot hashes is one that Spark can split.

Among n windows about n*n/2**129 pairs are expected to be taken for equal wrongly.

Defined cases: null text has no words; a text shorter than the window has no window; a null ``doc_id`` neither
lends nor loses words; rows that share a ``doc_id`` are judged each by its own text and never against each
other; a very long text is hashed and cut in runs of about 256 KB of words, so what a worker holds of it is the text
itself and 8 bytes a word of one run; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, mix64, plain, text_slices, word_chunks

#: An odd base, so that its powers have inverses modulo 2**64.
BASE = 0x9E3779B97F4A7C15 | 1
BASE_TWO = 0xC2B2AE3D27D4EB4F | 1
BUCKETS = 1 << 16
#: Bytes of text hashed at a time, and window hashes folded at a time.
SLICE, FOLD = 1 << 19, 1 << 18


def _powers(n: int, of: int) -> np.ndarray:
    p = np.full(n, of, np.uint64)
    if n:
        p[0] = 1
    return np.cumprod(p, dtype=np.uint64)


class Windows:
    """Rolling hashes of the windows of many texts, in turns of about ``most`` words.

    Sums of word hashes times powers of the base give every window's polynomial by one difference.  ``second`` gives a
    second, independent hash of each window, from other bits of the word hashes under another base.
    """

    def __init__(self, window: int, second: bool = False, most: int = 1 << 16):
        self.window, self.second, self.most = window, second, most
        self.powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def _sums(self, words: np.ndarray, at: np.ndarray, base: int) -> np.ndarray:
        n = len(words)
        if base not in self.powers or n > len(self.powers[base][0]):
            self.powers[base] = _powers(2 * n, base), _powers(2 * n, pow(base, -1, 1 << 64))
        up, down = self.powers[base]
        sums = np.zeros(n + 1, np.uint64)
        np.cumsum(words * up[:n], out=sums[1:])
        return mix64((sums[at + self.window] - sums[at]) * down[at])

    def _turn(self, held: list[tuple[int, int, np.ndarray]]) -> tuple[np.ndarray, ...]:
        w = self.window
        text, first, words = zip(*held, strict=True)
        lengths = np.array([len(x) for x in words], np.int64)
        many = lengths - w + 1
        doc = np.repeat(np.array(text, np.int32), many)
        inside = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
        at = inside + np.repeat(np.cumsum(lengths) - lengths, many)
        pos = (inside + np.repeat(np.array(first, np.int64), many)).astype(np.int32)
        words = np.concatenate(words)
        hashes = [self._sums(mix64(words), at, BASE)]
        if self.second:
            hashes.append(self._sums(mix64(words ^ np.uint64(BASE)), at, BASE_TWO))
        return (*hashes, doc, pos)

    def of(self, texts: list[str | None]) -> Iterator[tuple[np.ndarray, ...]]:
        """Turns of: hash (and second hash), index of the text, and start within the text, of every window."""
        digest, w = xxhash.xxh64_intdigest, self.window
        held, size = [], 0
        for i, text in enumerate(texts):
            before, pos = np.zeros(0, np.uint64), 0
            for words in word_chunks(text.encode("utf-8", "surrogatepass")) if text else ():
                hashed = np.concatenate((before, np.fromiter(map(digest, words), np.uint64, len(words))))
                if len(hashed) >= w:
                    held.append((i, pos, hashed))
                    size += len(hashed)
                    before = hashed[len(hashed) - w + 1 :]
                    pos += len(hashed) - w + 1
                else:
                    before = hashed
                if size >= self.most:
                    yield self._turn(held)
                    held, size = [], 0
        if held:
            yield self._turn(held)


def _count_windows(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        roll, held, size = Windows(window), [], 0
        for batch in batches:
            for part in text_slices(batch, budget=SLICE):
                ids = part.column("doc_id").to_numpy(zero_copy_only=False).astype(np.int64)
                for h, doc, _ in roll.of(part.column("text").to_pylist()):
                    held.append((h, ids[doc]))
                    size += len(h)
                    if size >= FOLD:
                        yield from _folded(held)
                        held, size = [], 0
        if held:
            yield from _folded(held)

    return run


def _folded(held: list[tuple[np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
    """Equal hashes as one row with the smallest doc_id; the largest gets a row where it differs."""
    h, owner = map(np.concatenate, zip(*held, strict=True))
    order = np.argsort(h)
    h, owner = h[order], owner[order]
    first = np.flatnonzero(np.concatenate(([True], h[1:] != h[:-1])))
    low, high = np.minimum.reduceat(owner, first), np.maximum.reduceat(owner, first)
    h, twice = h[first].view(np.int64), low != high
    yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(low)], names=["h", "doc_id"])
    if twice.any():
        yield pa.RecordBatch.from_arrays([pa.array(h[twice]), pa.array(high[twice])], names=["h", "doc_id"])


def _filter_rows(bits: int):
    """Bits of a filter for each bucket of hashes: rows come whole buckets at a time."""
    width = bits // BUCKETS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, bitmap = None, np.zeros(width, bool)
        for batch in batches:
            bucket = batch.column("bucket").to_numpy(zero_copy_only=False)
            h = batch.column("h").to_numpy(zero_copy_only=False).view(np.uint64)
            cuts = np.concatenate(([0], np.flatnonzero(np.diff(bucket)) + 1, [len(bucket)])) if len(bucket) else [0]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if bucket[a] != held:
                    if held is not None:
                        yield _filter_row(held, bitmap)
                    held, bitmap = bucket[a], np.zeros(width, bool)
                for bit in _bits(h[a:b], width):
                    bitmap[bit] = True
        if held is not None:
            yield _filter_row(held, bitmap)

    return run


def _filter_row(bucket: int, bitmap: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([int(bucket)], pa.int32()), pa.array([np.packbits(bitmap).tobytes()], pa.binary())], names=["bucket", "bits"])


def _bits(h: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Two bit places of a hash within its bucket's part of the filter."""
    return (h % np.uint64(width)).astype(np.int64), ((h >> np.uint64(24)) % np.uint64(width)).astype(np.int64)


def _candidates(window: int, bits: int, shared, places: bool):
    """Windows that may repeat: (h, h2, doc_id), and (mark, pos) if ``places``."""
    width = bits // BUCKETS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packed, roll = np.frombuffer(shared.value, np.uint8), Windows(window, second=True)
        for batch in batches:
            for part in text_slices(batch, budget=SLICE):
                ids = part.column("doc_id").to_numpy(zero_copy_only=False).astype(np.int64)
                marks = part.column("mark").to_numpy(zero_copy_only=False).astype(np.int64) if places else None
                for h, h2, doc, pos in roll.of(part.column("text").to_pylist()):
                    base = ((h >> np.uint64(48)).astype(np.int64) ^ (1 << 15)) * width
                    keep = np.ones(len(h), bool)
                    for bit in _bits(h, width):
                        at = base + bit
                        keep &= (packed[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1 == 1
                    if keep.any():
                        doc = doc[keep]
                        columns = {"h": h[keep].view(np.int64), "h2": h2[keep].view(np.int64), "doc_id": ids[doc]}
                        if places:
                            columns |= {"mark": marks[doc], "pos": pos[keep]}
                        yield pa.RecordBatch.from_arrays([pa.array(x) for x in columns.values()], names=list(columns))

    return run


def _intervals(hits: pa.Scalar, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Maximal removal intervals of a text's flagged windows, which come as bits of blocks of 64 starts."""
    blocks = hits.values
    of = blocks.field("block").to_numpy(zero_copy_only=False).astype(np.int64)
    order = np.argsort(of)
    bits = np.ascontiguousarray(blocks.field("bits").to_numpy(zero_copy_only=False)[order]).view(np.uint8)
    row, bit = np.nonzero(np.unpackbits(bits, bitorder="little").reshape(-1, 64))
    at = of[order][row] * 64 + bit
    gap = np.flatnonzero(np.diff(at) > window)
    return at[np.concatenate(([0], gap + 1))], at[np.concatenate((gap, [len(at) - 1]))] + window


def _keep_words(data: bytes, begin: np.ndarray, end: np.ndarray) -> tuple[int, str]:
    """Number of words, and those outside the intervals joined by one space."""
    n, kept, nxt = 0, [], 0
    for words in word_chunks(data):
        upto, left, last = n + len(words), [], n
        while nxt < len(begin) and begin[nxt] < upto:
            left += words[last - n : max(begin[nxt], last) - n]
            last = min(end[nxt], upto)
            if end[nxt] > upto:
                break
            nxt += 1
        left += words[last - n :]
        if left:
            kept.append(b" ".join(left))
        n = upto
    return n, b" ".join(kept).decode("utf-8", "surrogatepass")


def _cut(window: int):
    none = np.zeros(0, np.int64)
    span = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in text_slices(batch, budget=SLICE):
                rows = []
                for text, hits in zip(part.column("text").to_pylist(), part.column("hits"), strict=True):
                    begin, end = _intervals(hits, window) if hits.is_valid else (none, none)
                    n_words, kept = _keep_words(text.encode("utf-8", "surrogatepass") if text else b"", begin, end)
                    rows.append((n_words, int((end - begin).sum()), [{"start": a, "end": b} for a, b in zip(begin.tolist(), end.tolist(), strict=True)], kept))
                n_words, n_removed, spans, kept = zip(*rows, strict=True)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(spans, span), pa.array(kept, pa.string())], names=["doc_id", "n_words", "n_removed", "removed", "kept_text"])

    return run


def substring_dedup(docs: DataFrame, window: int = 50, filter_bits: int = 1 << 27) -> DataFrame:
    """Remove words covered by a window that also starts in a document with a smaller ``doc_id``.

    Returns per row: doc_id, n_words, n_removed, removed (maximal intervals of word numbers, end exclusive) and
    kept_text (kept words joined by one space).
    """
    spark = docs.sparkSession
    base = plain(docs, "doc_id", "text")
    known = base.where("doc_id IS NOT NULL AND text IS NOT NULL")
    counted = known.mapInArrow(_count_windows(window), "h long, doc_id long").repartition("h")
    repeated = counted.groupBy("h").agg(F.min("doc_id").alias("low"), F.max("doc_id").alias("high")).where("low < high").select("h")
    repeated = materialize(repeated, "windows")
    packed = np.zeros(filter_bits // 8, np.uint8)
    width = filter_bits // BUCKETS // 8
    by_bucket = repeated.select(F.shiftright("h", 48).cast("int").alias("bucket"), "h").repartition("bucket").sortWithinPartitions("bucket")
    for row in by_bucket.mapInArrow(_filter_rows(filter_bits), "bucket int, bits binary").toLocalIterator():
        start = (row.bucket + (1 << 15)) * width
        packed[start : start + width] = np.frombuffer(bytes(row.bits), np.uint8)
    shared = spark.sparkContext.broadcast(packed.tobytes())
    key = ["h", "h2"]
    maybe = known.mapInArrow(_candidates(window, filter_bits, shared, False), "h long, h2 long, doc_id long")
    first = maybe.groupBy(*key).agg(F.min("doc_id").alias("low"), F.max("doc_id").alias("high")).where("low < high").select(*key, "low")
    first = materialize(first, "firsts")
    marked = base.withColumn("mark", F.xxhash64("text"))
    placed = marked.where("doc_id IS NOT NULL AND text IS NOT NULL").mapInArrow(_candidates(window, filter_bits, shared, True), "h long, h2 long, doc_id long, mark long, pos int")
    # 64 starts a long: rows that repeat set the same bits, and a text's flags move as one bit a window at most
    flags = placed.join(first.hint("merge"), key).where("low < doc_id").groupBy("doc_id", "mark", F.expr("pos div 64").cast("int").alias("block")).agg(F.bit_or(F.expr("shiftleft(1L, pos % 64)")).alias("bits"))
    # written first, so that the windows' shuffle files are gone before the texts move
    hits = materialize(flags.groupBy("doc_id", "mark").agg(F.collect_list(F.struct("block", "bits")).alias("hits")), "flags")
    # neither side is broadcast at any size, as both grow with the corpus
    joined = marked.join(hits.hint("merge"), ["doc_id", "mark"], "left").select("doc_id", "text", "hits")
    return joined.mapInArrow(_cut(window), "doc_id long, n_words long, n_removed long, removed array<struct<start:int,end:int>>, kept_text string")
