"""Training-order materialisation of token ids: a keyed permutation of sequences, written as fixed-stride shards.

Documents are one stream of token ids, each document followed by an end id; sequence i is the i-th run of
``length`` ids of the stream, the last one filled up with end ids.  A keyed Feistel network over the least power of
four that holds all sequences, walked along its cycle until it lands inside, is a bijection of sequence numbers
to slots: no list of numbers is shuffled, and a slot's sequence is known without reading anything.  Shards are ranges
of slots; rows go straight to their range, so a shard is read in slot order and a run resumes at any slot.

A shard is a binary file of records of one size: the packed ids of a slot's sequence and one end byte, which Spark's text
writer puts after every record.  Slot s is record s % ``shard_rows`` of shard s // ``shard_rows`` and begins at that number
times the record size, so a reader seeks to any slot.  Spark's committer moves whole files into place, so a lost task
leaves no half shard; the size of every shard is compared with the manifest's numbers before the manifest is written.

Token ids come as packed bytes of ``width`` bytes an id, little end first.  ``piece_tokens`` makes ids of the pieces of a
public vocabulary; ``byte_tokens`` makes ids of UTF-8 bytes, which need no vocabulary file (0xFF never occurs in UTF-8
and ends a document).

Two passes over the input: the first adds up bytes a partition (one number a partition goes to the driver and, as a
broadcast table, to the tasks), the second cuts the stream.  Both read the same partitions; the second fails rather
than misplace a sequence if a partition's bytes differ.  The ids move once.

Defined cases: null tokens are left out; empty tokens are a document of its end id alone; a very long text is encoded in
runs that end at single spaces, which gives the same ids, and is cut like any other; a table without rows makes a
manifest of no sequences and no shard; repeated rows are repeated documents; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import mix64, plain, text_slices

ROUNDS = 4
BYTE_END = b"\xff"
#: The byte after every record, and the most bytes of a shard, which is read as one value.
RECORD_END, MOST_SHARD = "\n", 1 << 30
#: Words whose piece numbers a worker keeps.
MOST_KNOWN = 1 << 18


class Permutation:
    """A keyed bijection of range(n)."""

    def __init__(self, n: int, key: int):
        self.n = n
        self.half = np.uint64(max(1, ((max(n, 2) - 1).bit_length() + 1) // 2))
        self.low = np.uint64((1 << int(self.half)) - 1)
        self.keys = mix64(np.arange(1, ROUNDS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(key & (1 << 64) - 1))

    def _round(self, x: np.ndarray, key: np.uint64) -> np.ndarray:
        return mix64(x ^ key) & self.low

    def _once(self, x: np.ndarray) -> np.ndarray:
        left, right = x >> self.half, x & self.low
        for k in self.keys:
            left, right = right, left ^ self._round(right, k)
        return (left << self.half) | right

    def _back(self, x: np.ndarray) -> np.ndarray:
        left, right = x >> self.half, x & self.low
        for k in self.keys[::-1]:
            left, right = right ^ self._round(left, k), left
        return (left << self.half) | right

    def _walk(self, x: np.ndarray, step) -> np.ndarray:
        x = step(np.asarray(x, np.uint64))
        while (out := x >= self.n).any():
            x[out] = step(x[out])
        return x.astype(np.int64)

    def slot(self, index: np.ndarray) -> np.ndarray:
        """Slot of each sequence number."""
        return self._walk(index, self._once)

    def index(self, slot: np.ndarray) -> np.ndarray:
        """Sequence number at each slot."""
        return self._walk(slot, self._back)


def byte_tokens(text: Column) -> Column:
    """UTF-8 bytes as one-byte token ids."""
    return text.cast("binary")


def _runs_of(text: str, size: int) -> Iterator[str]:
    """A text in runs of about ``size`` characters.  A run ends at a space with no other beside it, which is left out:
    the encoder puts one before each run."""
    at = 0
    while len(text) - at > size:
        cut = at + size
        while (cut := text.find(" ", cut)) >= 0 and (text[cut - 1] == " " or text[cut + 1 : cut + 2] in (" ", "")):
            cut += 1
        if cut < 0:
            break
        yield text[at:cut]
        at = cut + 1
    yield text[at:]


def piece_tokens(docs: DataFrame, model_file: str, run_chars: int = 1 << 16) -> DataFrame:
    """(doc_id, tokens): the piece numbers of every text as packed 16-bit ids; null texts stay null.

    ``model_file`` is read by the driver; its vocabulary must have at most 65,536 pieces, none of which goes on past a
    space.  Recurring words are encoded once.
    """
    with open(model_file, "rb") as f:
        model = f.read()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_proto=model)
        if sp.get_piece_size() > 1 << 16:
            raise ValueError("piece numbers need more than 16 bits")

        known: dict[str, bytes] = {}

        def packed(rows: list[list[int]]) -> Iterator[bytes]:
            flat = np.array([x for row in rows for x in row], "<u2").tobytes()
            ends = np.cumsum([2 * len(row) for row in rows]).tolist()
            return (flat[a:b] for a, b in zip([0, *ends[:-1]], ends, strict=True)) if rows else iter(())

        def ids(text: str | None, words: list[str] | None) -> bytes | None:
            if text is None:
                return None
            return b"".join(map(known.__getitem__, words)) if words else b"".join(packed([sp.encode(x) for x in _runs_of(text, run_chars)]))

        for batch in batches:
            for part in text_slices(batch, budget=1 << 20):
                texts = part.column("text").to_pylist()
                # no piece goes on past a space: a text whose words stand one space apart is the pieces of its words
                split = [t.split(" ") if t and "  " not in t and t[0] != " " != t[-1] else None for t in texts]
                new = list({w for words in split if words for w in words}.difference(known))
                if len(known) + len(new) > MOST_KNOWN:
                    known.clear()
                    new = list({w for words in split if words for w in words})
                known.update(zip(new, packed(sp.encode(new)), strict=True))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(map(ids, texts, split), pa.binary())], names=["doc_id", "tokens"])

    return plain(docs, "doc_id", "text").mapInArrow(run, "doc_id long, tokens binary")


def _cut_rows(bases, stride: int, end: bytes, total: int, order: Permutation):
    """Rows of tokens -> (slot, at, piece): the pieces of sequences that lie in this partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        start, size = bases.value.get(part, (0, 0))
        at, held, seen = start, b"", 0

        def out(pieces: list[bytes], first: int, offset: int) -> pa.RecordBatch:
            index = np.arange(first, first + len(pieces))
            offsets = np.zeros(len(pieces), np.int32)
            offsets[:1] = offset
            return pa.RecordBatch.from_arrays([pa.array(order.slot(index)), pa.array(index), pa.array(offsets), pa.array(pieces, pa.binary())], names=["slot", "seq", "at", "piece"])

        for batch in batches:
            for some in text_slices(batch, "tokens", budget=1 << 20):
                more = b"".join([y for x in some.column("tokens").to_pylist() for y in (x, end)])
                seen += len(more)
                held += more
                first, offset = divmod(at, stride)
                whole = (offset + len(held)) // stride
                if whole:
                    cuts = [0] + [stride * (i + 1) - offset for i in range(whole)]
                    for b in range(0, whole, 2000):
                        pieces = [held[x:y] for x, y in zip(cuts[b : b + 2000], cuts[b + 1 : b + 2001], strict=False)]
                        yield out(pieces, first + b, offset if b == 0 else 0)
                    at += cuts[-1]
                    held = held[cuts[-1] :]
        if seen != size:
            raise RuntimeError(f"partition {part} had {size} bytes at first and {seen} now; write the input to a table first")
        if seen and start + seen == total:
            held += end * ((-total % stride) // len(end))
        if held:
            yield out([held], at // stride, at % stride)

    return run


def _join_rows(stride: int):
    """Pieces in order of slot and offset -> whole sequences as records; raises if a slot is not whole."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slot, parts, size = None, [], 0
        for batch in batches:
            rows = []
            for s, at, piece in zip(batch.column("slot").to_pylist(), batch.column("at").to_pylist(), batch.column("piece").to_pylist(), strict=True):
                if s != slot and size:
                    raise RuntimeError(f"slot {slot} has {size} of {stride} bytes")
                if at != size:
                    raise RuntimeError(f"slot {s} goes on at byte {at} after {size} bytes")
                slot = s
                parts.append(piece)
                size += len(piece)
                if size == stride:
                    rows.append(b"".join(parts))
                    parts, size = [], 0
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(rows, pa.binary())], names=["tokens"])
        if size:
            raise RuntimeError(f"slot {slot} has {size} of {stride} bytes")

    return run


def _shard_sizes(spark: SparkSession, path: str) -> dict[int, tuple[str, int]]:
    """File and size of each shard by its number."""
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs
    where = hadoop.Path(f"{path}/shards")
    fs = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    files = [x for x in fs.listStatus(where) if x.getPath().getName().startswith("part-") and x.getLen()]
    return {int(x.getPath().getName().split("-")[1]): (x.getPath().toString(), x.getLen()) for x in files}


def write_training_order(docs: DataFrame, path: str, tokens: Column, length: int = 2048, width: int = 1, end: bytes = BYTE_END, shard_rows: int = 2048, key: int = 20) -> dict:
    """Write the sequences of ``tokens`` (packed ids) of all rows under ``path``; returns the manifest.

    ``path``/shards has one binary file a shard, records in slot order and of one size; ``path``/manifest has one row,
    written last: a path without it is unfinished.
    """
    spark, stride = docs.sparkSession, length * width
    if len(end) != width:
        raise ValueError("the end id must have the width of an id")
    stream = docs.select(tokens.alias("tokens")).where("tokens IS NOT NULL")
    sums = stream.groupBy(F.spark_partition_id().alias("p")).agg(F.sum(F.octet_length("tokens") + width).cast("long").alias("n")).collect()
    bases, total = {}, 0
    for row in sorted(sums, key=lambda r: r.p):
        bases[row.p] = (total, row.n)
        total += row.n
    n = -(-total // stride)
    if shard_rows * (stride + 1) > MOST_SHARD:
        raise ValueError(f"a shard of {shard_rows} sequences has over {MOST_SHARD} bytes")
    manifest = {"sequences": n, "length": length, "width": width, "shard_rows": shard_rows, "key": key, "tokens": total // width}
    shards = max(1, -(-n // shard_rows))
    if n:
        cut = stream.mapInArrow(_cut_rows(spark.sparkContext.broadcast(bases), stride, end, total, Permutation(n, key)), "slot long, seq long, at int, piece binary")
        dealt = cut.repartitionById(shards, F.expr(f"cast(slot div {shard_rows} as int)")).sortWithinPartitions("slot", "at")
        whole = dealt.mapInArrow(_join_rows(stride), "tokens binary")
        whole.select(F.col("tokens").cast("string").alias("value")).write.option("lineSep", RECORD_END).text(f"{path}/shards")
        found = _shard_sizes(spark, path)
        wanted = {i: min(shard_rows, n - i * shard_rows) * (stride + 1) for i in range(shards)}
        if wrong := [i for i, size in wanted.items() if found.get(i, ("", 0))[1] != size]:
            raise RuntimeError(f"{len(wrong)} shards are not whole, the first is {wrong[0]}")
    spark.createDataFrame([tuple(manifest.values())], ", ".join(f"{k} long" for k in manifest)).coalesce(1).write.parquet(f"{path}/manifest")
    return manifest


def _record_rows(first: int, last: int, m):
    """Shard files -> (slot, shard, seq, tokens) of the slots in [first, last)."""
    stride = m.length * m.width + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        order = Permutation(m.sequences, m.key)
        for batch in batches:
            for path, content in zip(batch.column("path").to_pylist(), batch.column("content"), strict=True):
                shard, data = int(path.rsplit("/", 1)[1].split("-")[1]), content.as_buffer()
                low = shard * m.shard_rows
                for a in range(max(first, low), min(last, low + len(data) // stride), 256):
                    slots = np.arange(a, min(a + 256, last, low + len(data) // stride))
                    rows = [data[(s - low) * stride : (s - low + 1) * stride - 1].to_pybytes() for s in slots.tolist()]
                    yield pa.RecordBatch.from_arrays([pa.array(slots), pa.array(np.full(len(slots), shard, np.int32)), pa.array(order.index(slots)), pa.array(rows, pa.binary())], names=["slot", "shard", "seq", "tokens"])

    return run


def read_slots(spark: SparkSession, path: str, first: int = 0, count: int | None = None) -> DataFrame:
    """(slot, shard, seq, tokens) at slots first, first + 1, ... of a finished path; only the shards that hold them are read."""
    m = spark.read.parquet(f"{path}/manifest").first()
    last = m.sequences if count is None else min(m.sequences, first + count)
    schema = "slot long, shard int, seq long, tokens binary"
    if last <= first:
        return spark.createDataFrame([], schema)
    some = [file for shard, (file, _) in _shard_sizes(spark, path).items() if first // m.shard_rows <= shard <= (last - 1) // m.shard_rows]
    files = spark.read.format("binaryFile").load(some).select("path", "content")
    return files.mapInArrow(_record_rows(first, last, m), schema)


def read_at(spark: SparkSession, path: str, slot: int) -> np.ndarray:
    """The ids of one slot, by a seek in its shard: how a reader that resumes goes on."""
    m = spark.read.parquet(f"{path}/manifest").first()
    stride = m.length * m.width
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs
    where = hadoop.Path(_shard_sizes(spark, path)[slot // m.shard_rows][0])
    stream = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).open(where)
    try:
        stream.seek(slot % m.shard_rows * (stride + 1))
        raw = bytes(stream.readNBytes(stride))
    finally:
        stream.close()
    return np.frombuffer(raw, f"<u{m.width}") if m.width in (1, 2, 4, 8) else np.frombuffer(raw, np.uint8)
