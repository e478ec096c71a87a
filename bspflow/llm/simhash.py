"""SimHash near-duplicates through an inverted index of byte positions with count filtering.

A fingerprint of 64 bits is 8 bytes in 8 positions.  Two fingerprints with at most 4 differing bits share at least 4
positional bytes, so 4 is the guaranteed minimum of matches.  A posting list of one positional byte would hold a 256th of
the corpus, so a list is keyed by three positions with their bytes.  The first three positions that a wanted pair shares
are among the first seven, so 35 sets of three find every such pair.  Pairs that meet in a list have their shared
positional bytes tallied over all eight positions; a pair goes on only if the tally reaches 4 (most pairs that meet by
chance share just the three), and only from the list of its first three shared positions, so it is looked at once.
What is left is verified by its differing bits.

Copies fold first: the index holds distinct fingerprints, and a list emits a forest of its verified pairs, never
all pairs.  A list of more than ``most`` members is passed on, unpaired: its members are posted again under a fourth
position behind the three (with 70 sets of four in all), and lists of those that are still too long under four of the
eight half bytes that are left (4 of 8 must match again); these have 16 free bits, so 65,536 members is their bound.

Defined cases: null, empty or blank text has fingerprint zero and links like any other; rows with a null
``doc_id`` get a fingerprint and take part as documents without an id (component by the other members, null if
alone); repeated rows get equal rows; a very long text is hashed in runs of about 256 KB of words; an empty table gives
an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize, mix64, plain, text_slices, word_chunks
from .components import components

SHINGLE, SEED = 4, 42
#: Half-byte sets of the last index, and position sets of the first.
SETS = list(combinations(range(8), 4))
FIRST_SETS = list(combinations(range(7), 3))
#: Which bits of a byte are set, by its value.
_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1).astype(np.int64)


def _shingle_hashes(text: str, shingle: int, seed: int) -> Iterator[np.ndarray]:
    """Hashes of the shingles of a text, by runs of its words; of the whole sequence if it is shorter than a shingle."""
    digest, before, any_ = xxhash.xxh64_intdigest, [], False
    for words in word_chunks(text.encode("utf-8", "surrogatepass").lower()):
        words = before + words
        before = words[1 - shingle :]
        if len(words) < shingle:
            continue
        joined, any_ = b" ".join(words), True
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
        starts = [0, *ends[:-shingle].tolist()]
        yield np.fromiter((digest(joined[a:b], seed) for a, b in zip(starts, (ends[shingle - 1 :] - 1).tolist(), strict=True)), np.uint64, len(starts))
    if before and not any_:
        yield np.array([digest(b" ".join(before), seed)], np.uint64)


def fingerprints(texts: list[str | None], shingle: int = SHINGLE, seed: int = SEED, most: int = 1 << 16) -> np.ndarray:
    """Majority-bit fingerprints of word shingles, as unsigned 64-bit numbers."""
    tally, counts = np.zeros((len(texts), 8, 8), np.int64), np.zeros(len(texts), np.int64)
    held, size = [], 0

    def add() -> None:
        by = np.concatenate([h for _, h in held]).astype(">u8").view(np.uint8).reshape(-1, 8)
        who, many = np.array([i for i, _ in held]), np.array([len(h) for _, h in held])
        row = np.repeat(np.arange(len(held)) * 256, many)
        np.add.at(counts, who, many)
        for k in range(8):
            np.add.at(tally[:, k], who, np.bincount(row + by[:, k], minlength=len(held) * 256).reshape(-1, 256) @ _BITS)

    for i, text in enumerate(texts):
        for hashes in _shingle_hashes(text, shingle, seed) if text else ():
            held.append((i, hashes))
            size += len(hashes)
            if size >= most:
                add()
                held, size = [], 0
    if held:
        add()
    return np.packbits(tally * 2 > counts[:, None, None], axis=2)[:, :, 0].copy().view(">u8")[:, 0].astype(np.uint64)


def _print_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The text of each row becomes its fingerprint; other columns stay."""
    for batch in batches:
        for part in text_slices(batch, budget=1 << 18):
            fp = fingerprints(part.column("text").to_pylist())
            rest = [n for n in part.schema.names if n != "text"]
            yield pa.RecordBatch.from_arrays([*[part.column(n) for n in rest], pa.array(fp.view(np.int64))], names=[*rest, "fp"])


def _forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The links of a star for each component of the given pairs."""
    nodes, at = np.unique(np.concatenate((a, b)), return_inverse=True)
    i, j = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[i], label[j])
        new = label.copy()
        np.minimum.at(new, label[i], low)
        np.minimum.at(new, label[j], low)
        while (new[new] != new).any():
            new = new[new]
        new = new[label]
        if (new == label).all():
            break
        label = new
    other = label != np.arange(len(nodes))
    return nodes[other], nodes[label[other]]


def _pairs(fp: np.ndarray, group: np.ndarray, sets: np.ndarray, named: int, most_bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Verified links among members of equal group; members are sorted by group.

    Shared positional bytes are tallied first; a pair must reach 8 - ``most_bits`` of them, and the first ``named`` of
    those must be the list's own (0: any list will do).
    """
    left, right = [], []
    live = np.arange(len(fp))
    step = 1
    places = 1 << np.arange(8)
    while True:
        live = live[live + step < len(fp)]
        live = live[group[live] == group[live + step]]
        if not len(live):
            break
        x = fp[live] ^ fp[live + step]
        shared = x.astype(">u8").view(np.uint8).reshape(-1, 8) == 0
        keep = shared.sum(1) >= 8 - most_bits
        if named:
            first = shared & (np.cumsum(shared, axis=1) <= named)
            keep &= first @ places == sets[live]
        at = live[keep]
        at = at[np.bitwise_count(x[keep]) <= most_bits]
        if len(at):
            left.append(fp[at])
            right.append(fp[at + step])
        step += 1
    if not left:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    return _forest(np.concatenate(left), np.concatenate(right))


def _link_rows(most_bits: int, most: int, named: int):
    """Rows (key, mask, fp) sorted by key -> links (a, b); lists of over ``most`` members come out with b null."""

    def out(a, b, mask=None):
        none = b is None
        return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.nulls(len(a), pa.int64()) if none else pa.array(b.view(np.int64)), pa.array(mask if none else np.zeros(len(a), np.int32))], names=["a", "b", "mask"])

    def done(key, mask, fp):
        a, b = _pairs(fp, key, mask, named, most_bits)
        if len(a):
            yield out(a, b)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        count, last, over = 0, None, False
        for batch in batches:
            if not batch.num_rows:
                continue
            key = batch.column("key").to_numpy(zero_copy_only=False)
            mask = batch.column("mask").to_numpy(zero_copy_only=False)
            fp = batch.column("fp").to_numpy(zero_copy_only=False).view(np.uint64)
            cuts = np.flatnonzero(np.diff(key)) + 1
            if last is not None and key[0] != last:
                cuts = np.concatenate(([0], cuts))
            head = cuts[0] if len(cuts) else len(key)
            tail = cuts[-1] if len(cuts) else len(key)
            if head:
                if over or count + head > most:
                    for _, m, f in held:
                        yield out(f, None, m)
                    held, over = [], True
                    yield out(fp[:head], None, mask[:head])
                else:
                    held.append((key[:head], mask[:head], fp[:head]))
                    count += head
            if len(cuts):
                if held:
                    yield from done(*map(np.concatenate, zip(*held, strict=True)))
                inner = slice(head, tail)
                if tail > head:
                    k, m, f = key[inner], mask[inner], fp[inner]
                    sizes = np.diff(np.concatenate((np.flatnonzero(np.concatenate(([True], k[1:] != k[:-1]))), [len(k)])))
                    big = np.repeat(sizes > most, sizes)
                    if big.any():
                        yield out(f[big], None, m[big])
                    yield from done(k[~big], m[~big], f[~big])
                held, count, over = [(key[tail:], mask[tail:], fp[tail:])], len(key) - tail, False
            last = key[-1]
        if held and not over:
            yield from done(*map(np.concatenate, zip(*held, strict=True)))

    return run


def _postings(fp: Column) -> Column:
    """The 35 keys of a fingerprint: which 3 positions, and their bytes."""
    byte = [F.shiftrightunsigned(fp, 56 - 8 * k).bitwiseAND(F.lit(255).cast("long")) for k in range(8)]
    entries = []
    for n, positions in enumerate(FIRST_SETS):
        key = F.lit(n).cast("long")
        for k in positions:
            key = F.shiftleft(key, 8).bitwiseOR(byte[k])
        entries.append(F.struct(key.alias("key"), F.lit(sum(1 << k for k in positions)).alias("mask")))
    return F.array(*entries)


def _fourth_postings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Members of an overfull list of 3 positions, under each position behind these as well."""
    for batch in batches:
        fp = batch.column("a").to_numpy(zero_copy_only=False).view(np.uint64)
        mask = batch.column("mask").to_numpy(zero_copy_only=False)
        for held in np.unique(mask).tolist():
            f = fp[mask == held]
            for k in range(held.bit_length(), 8):
                wider = held | 1 << k
                fixed = np.uint64(sum(255 << (56 - 8 * j) for j in range(8) if wider >> j & 1))
                key = mix64((f & fixed) + np.uint64(wider))
                yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(np.full(len(f), wider, np.int32)), pa.array(f.view(np.int64))], names=["key", "mask", "fp"])


def _half_byte_postings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Members of an overfull list, by the half bytes of the 4 positions which that list leaves free."""
    for batch in batches:
        fp = batch.column("a").to_numpy(zero_copy_only=False).view(np.uint64)
        mask = batch.column("mask").to_numpy(zero_copy_only=False)
        for held in np.unique(mask):
            f = fp[mask == held]
            free = [k for k in range(8) if not held >> k & 1]
            halves = [(f >> np.uint64(60 - 8 * k - 4 * h)) & np.uint64(15) for k in free for h in (0, 1)]
            fixed = np.zeros(len(f), np.uint64)
            for k in range(8):
                if held >> k & 1:
                    fixed = (fixed << np.uint64(8)) | ((f >> np.uint64(56 - 8 * k)) & np.uint64(255))
            for n, chosen in enumerate(SETS):
                sub = np.full(len(f), n, np.uint64)
                for k in chosen:
                    sub = (sub << np.uint64(4)) | halves[k]
                m = np.full(len(f), int(held) << 8 | n, np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(fixed.view(np.int64)), pa.array((sub | (np.uint64(held) << np.uint64(32))).view(np.int64)), pa.array(m), pa.array(f.view(np.int64))], names=["fixed", "key", "mask", "fp"])


def _listed(posted: DataFrame, most_bits: int, most: int, named: int) -> DataFrame:
    """Links of posting lists, and members of overfull ones (b null)."""
    dealt = posted.repartition("key").sortWithinPartitions("key", "fp").select("key", "mask", "fp")
    return dealt.mapInArrow(_link_rows(most_bits, most, named), "a long, b long, mask int")


def simhash_links(prints: DataFrame, most_bits: int = 4, most: int = 4096) -> DataFrame:
    """Links (a, b) between distinct fingerprints ``prints``(fp), enough to connect all pairs within ``most_bits``."""
    if most_bits > 4:
        raise ValueError("4 shared bytes are guaranteed for at most 4 differing bits")
    if most > 1 << 16:
        raise ValueError("lists of the last index have 65,536 members at most")
    parts = int(prints.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    # few bytes a fingerprint, but 35 rows each: spread them before they grow
    distinct = prints.select("fp").distinct().repartition(parts, "fp")
    found = materialize(_listed(distinct.select("fp", F.inline(_postings(F.col("fp")))), most_bits, most, 3), "pairs")
    links, over = found.where("b IS NOT NULL").select("a", "b"), found.where("b IS NULL").select("a", "mask")
    if not over.limit(1).count():
        return links
    found = materialize(_listed(over.mapInArrow(_fourth_postings, "key long, mask int, fp long"), most_bits, most, 4), "pairs")
    links, over = links.unionByName(found.where("b IS NOT NULL").select("a", "b")), found.where("b IS NULL").select("a", "mask")
    if not over.limit(1).count():
        return links
    again = over.mapInArrow(_half_byte_postings, "fixed long, key long, mask int, fp long").withColumn("key", F.xxhash64("fixed", "key"))
    found = materialize(_listed(again, most_bits, 1 << 16, 0), "pairs")
    if found.where("b IS NULL").limit(1).count():
        raise RuntimeError("a half-byte list has more members than its free bits allow")
    return links.unionByName(found.select("a", "b"))


def near_duplicate_components(docs: DataFrame, most_bits: int = 4, most: int = 4096, row_key: str | None = None) -> DataFrame:
    """Fingerprint and component of every document.

    Returns doc_id, fp (the fingerprint's bits as a signed long), component_id (the smallest doc_id reachable
    over links of at most ``most_bits`` differing bits) and component (its smallest fingerprint, which tells components
    apart whose smallest doc_id is the same or null).  ``row_key`` names a binary column that comes back with its rows.
    """
    carried = [row_key] if row_key else []
    kinds = "doc_id long, " + "".join(f"`{c}` binary, " for c in carried) + "fp long"
    prints = materialize(plain(docs, "doc_id", *carried, "text").mapInArrow(_print_rows, kinds), "prints")
    owners = prints.groupBy("fp").agg(F.min("doc_id").alias("low"))
    links = simhash_links(owners, most_bits, most)
    class_of = components(links)
    named = owners.join(class_of.withColumnRenamed("node", "fp"), "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    lowest = named.groupBy("component").agg(F.min("low").alias("component_id"))
    told = named.select("fp", "component").join(lowest, "component").select("fp", "component_id", "component")
    return prints.join(told, "fp").select("doc_id", *carried, "fp", "component_id", "component")
