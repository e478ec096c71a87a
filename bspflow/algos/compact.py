"""De Bruijn units straight from reads, without a row for each k-mer.

A unit is an unbranched path, so each read crosses it from end to end or stops inside it.  Reads are held in chunks of
text.  A chunk asks about its k-mers and gets a byte for each place: stretches of consecutive k-mers go as text to the
parts that hold them (a k-mer's part follows from its smallest hashed m-mer, so neighbours mostly share one), a part
sorts its k-mers and answers in the order it was asked.  The answer says where the graph branches, and where some read
starts or ends within a path.  Cut at all of these, the pieces of reads are the same pieces in every read: the place
that owns a piece's first k-mer emits it once, with the k-mer's count.  Only pieces that a read's start or end has
cut from each other are still to be joined, at most two for each read.

A read is [0-9a-z]* and k is at most 12, so that a k-mer is a number below 36^12 whose order is that of the text.
Reads longer than a chunk are dealt in pieces that share a k-mer, which counts once.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .structure import cut, kept, min_label

BASE, START, MORE = 36, 36, 37
#: Letters of a chunk, and k-mers that a part holds; so many links among pieces one task labels, more are labelled in rounds.
CHUNK, PART, FEW = 1 << 20, 1_000_000, 1_000_000
#: Bits of the filter of places in doubt, as a power of two: 8 MB.
FILTER = 26
NUMBER = np.full(256, 255, np.uint8)
NUMBER[np.frombuffer(b"0123456789abcdefghijklmnopqrstuvwxyz\n\r", np.uint8)] = np.arange(38)
LETTER = np.frombuffer(b"0123456789abcdefghijklmnopqrstuvwxyz", np.uint8)
#: What a place is told: branches after or before it, a read ends or starts here inside a path, it owns its k-mer or its edge.
OUT, IN, ENDS, STARTS, OWN, EDGE = 1, 2, 4, 8, 16, 32


def _pack(x: np.ndarray) -> bytes:
    return len(x.view(np.uint8)).to_bytes(8, "little") + pa.compress(x.tobytes(), codec="zstd", asbytes=True)


def _unpack(b: bytes, kind=np.uint8) -> np.ndarray:
    return np.frombuffer(pa.decompress(b[8:], int.from_bytes(b[:8], "little"), codec="zstd", asbytes=True), kind)


def _spread(first: np.ndarray, many: np.ndarray) -> np.ndarray:
    """first[j], first[j] + 1, ... many[j] of them, for each j in turn."""
    ends = np.cumsum(many)
    return np.repeat(first - (ends - many), many) + np.arange(int(ends[-1]) if len(ends) else 0)


def _texts(data: np.ndarray, many: np.ndarray) -> pa.Array:
    """Strings of ``many`` bytes each out of the bytes of all of them."""
    ends = np.concatenate(([0], np.cumsum(many))).astype(np.int32)
    return pa.Array.from_buffers(pa.string(), len(many), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(data))])


def _rows(schema: pa.Schema, **columns) -> pa.Table:
    n = len(next(iter(columns.values())))
    return pa.table([columns[f.name] if isinstance(columns.get(f.name), pa.Array) else pa.array(columns[f.name], f.type) if f.name in columns else pa.nulls(n, f.type) for f in schema], schema=schema)


# ---------------------------------------------------------------- chunks of reads


def _varied(read: str, k: int, least: int) -> bool:
    """Whether a read has ``least`` different k-mers."""
    n = len(read) - k + 1
    return n >= least and any(len({read[i : i + k] for i in range(upto)}) >= least for upto in (min(n, 2 * least), n))


def _chunks_of(k: int, least: int | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        number = TaskContext.get().partitionId() << 32
        open_: dict[bool, list[str]] = {True: [], False: []}
        size = {True: 0, False: 0}

        def close(kind: bool) -> pa.RecordBatch:
            nonlocal number
            text = np.frombuffer(("".join(open_[kind]) + "\n").encode(), np.uint8)
            if (NUMBER[text] == 255).any():
                raise ValueError("reads hold letters other than 0-9 and a-z")
            open_[kind], size[kind], number = [], 0, number + 1
            return pa.RecordBatch.from_arrays([pa.array([number - 1], pa.int64()), pa.array([kind]), pa.array([_pack(text)], pa.binary())], names=["chunk", "sure", "text"])

        for batch in batches:
            for read in batch.column(0).to_pylist():
                if read is None or len(read) < k:
                    continue
                kind = least is None or _varied(read, k, least)
                for at in range(0, max(1, len(read) - k), CHUNK):
                    piece = read[at : at + CHUNK + k]
                    open_[kind].append(("\r" if at else "\n") + piece)
                    size[kind] += len(piece)
                    if size[kind] >= CHUNK:
                        yield close(kind)
        for kind in (True, False):
            if open_[kind]:
                yield close(kind)

    return run


def chunks(read: DataFrame, k: int, least: int | None = None) -> DataFrame:
    """(chunk, sure, text): reads of at least k letters, packed.  With ``least``, reads of fewer different k-mers than
    that are in chunks of their own, that are not sure."""
    if k > 12:
        raise ValueError("k is at most 12")
    return cut(read.select("read").mapInArrow(_chunks_of(k, least), "chunk long, sure boolean, text binary"))


def parts_for(held: DataFrame) -> int:
    """Parts that the k-mers of chunks are dealt to."""
    return max(1, -(-held.count() * CHUNK // PART))


# ---------------------------------------------------------------- what a chunk asks


def _codes(number: np.ndarray, at: np.ndarray, k: int) -> np.ndarray:
    code = np.zeros(len(at), np.int64)
    for j in range(k):
        code *= BASE
        code += number[at + j]
    return code


def _places(text: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Where k-mers begin in a chunk, and the k-mers as numbers."""
    if len(text) < k:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    number = NUMBER[text]
    marks = np.concatenate(([0], np.cumsum(number >= START, dtype=np.int32)))
    place = np.flatnonzero(marks[k:] == marks[:-k])
    long, n = number.astype(np.int64), len(text) - k + 1
    code = np.zeros(n, np.int64)
    for j in range(k):
        code *= BASE
        code += long[j : j + n]
    return place, code[place]


def _stretches(text: np.ndarray, k: int, parts: int):
    """(places, codes, first, many, part): k-mer places of a chunk, and its stretches by part: where each begins among the places and how many it has."""
    place, code = _places(text, k)
    if len(text) < k:
        none = np.zeros(0, np.int64)
        return place, code, none, none, none
    long, m = NUMBER[text].astype(np.int64), min(5, k)
    n = len(text) - k + 1
    small = np.zeros(len(text) - m + 1, np.int64)
    for j in range(m):
        small *= BASE
        small += long[j : j + len(small)]
    hashed = ((small + 1).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(24)
    least = hashed[:n].copy()
    for j in range(1, k - m + 1):
        np.minimum(least, hashed[j : j + n], out=least)
    part = (((least[place] * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(32)) % np.uint64(parts)).astype(np.int32)
    new = np.ones(len(place), bool)
    new[1:] = (place[1:] != place[:-1] + 1) | (part[1:] != part[:-1])
    first = np.flatnonzero(new)
    many = np.diff(np.append(first, len(place)))
    order = np.argsort(part[first], kind="stable")
    first, many = first[order], many[order]
    return place, code, first, many, part[first]


def _ask(k: int, parts: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk, sure, packed in zip(*(batch.column(c).to_pylist() for c in ("chunk", "sure", "text")), strict=True):
                text = _unpack(packed)
                place, _, first, many, part = _stretches(text, k, parts)
                where = np.flatnonzero(np.diff(part, prepend=-1))
                rows = []
                for a, b in zip(where, np.append(where[1:], len(part)), strict=True):
                    said = text[_spread(place[first[a:b]] - 1, many[a:b] + k + 1)]
                    rows.append((int(part[a]), _pack(said), _pack(many[a:b].astype(np.uint32))))
                if rows:
                    p, said, lens = zip(*rows, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array(p, pa.int32()), pa.array([chunk] * len(p), pa.int64()), pa.array([sure] * len(p)), pa.array(said, pa.binary()), pa.array(lens, pa.binary())], names=["part", "chunk", "sure", "said", "lens"])

    return run


def asked(held: DataFrame, k: int, parts: int) -> DataFrame:
    return held.mapInArrow(_ask(k, parts), "part int, chunk long, sure boolean, said binary, lens binary")


class _Part:
    """The k-mers of a part, sorted: ``order`` of places, ``heads`` of equal ones, and letters before and after as bits."""

    def __init__(self, rows: pa.Table, k: int):
        rows = rows.sort_by("chunk")
        self.chunks, self.sure = rows["chunk"].to_pylist(), rows["sure"].to_pylist()
        code, before, after, self.sizes = [], [], [], []
        for said, lens in zip(rows["said"], rows["lens"], strict=True):
            many = _unpack(lens.as_py(), np.uint32).astype(np.int64)
            number = NUMBER[_unpack(said.as_py())]
            wide = many + k + 1
            at = _spread(np.cumsum(wide) - wide + 1, many)
            code.append(_codes(number, at, k))
            before.append(number[at - 1])
            after.append(number[at + k])
            self.sizes.append(len(at))
        code = np.concatenate(code)
        self.order = np.argsort(code)
        code = code[self.order]
        self.heads = np.flatnonzero(np.concatenate(([True], code[1:] != code[:-1])))
        self.code = code[self.heads]
        self.before, self.after = np.concatenate(before)[self.order], np.concatenate(after)[self.order]
        self.many = np.diff(np.append(self.heads, len(code)))
        self.count = self.many - np.add.reduceat(self.before == MORE, self.heads, dtype=np.int64)

    def letters(self, number: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of each k-mer: how many different letters stand there, and whether a read's end does."""
        bits = np.bitwise_or.reduceat(np.int64(1) << number.astype(np.int64), self.heads)
        return np.bitwise_count(bits & ((1 << BASE) - 1)), bits >> BASE != 0


ANSWER = "chunk long, part int, told binary, counts binary"


def _answer(k: int, least: int | None):
    """One byte a place; with ``least``, whether the k-mer has that count."""

    def run(rows: pa.Table) -> pa.Table:
        p = _Part(rows, k)
        told = np.empty(len(p.order), np.uint8)
        counts = np.zeros(len(p.order), np.int64)
        if least is not None:
            told[p.order] = np.repeat(p.count >= least, p.many)
        else:
            (out, ends), (in_, starts) = p.letters(p.after), p.letters(p.before)
            flags = (out > 1) * OUT + (in_ > 1) * IN + (ends & (out == 1)) * ENDS + (starts & (in_ == 1)) * STARTS
            flags = np.repeat(flags.astype(np.uint8), p.many)
            flags[p.heads] |= OWN
            group = np.repeat(np.arange(len(p.heads), dtype=np.int64), p.many)
            goes = np.flatnonzero(p.after < BASE)
            fork = out[group[goes]] > 1
            one = goes[~fork]
            flags[one[np.flatnonzero(np.diff(group[one], prepend=-1))]] |= EDGE
            many = goes[fork]
            flags[many[np.unique(group[many] * 64 + p.after[many], return_index=True)[1]]] |= EDGE
            told[p.order] = flags
            counts[p.order[p.heads]] = p.count
        ends = np.cumsum(p.sizes)
        spans = [slice(b - a, b) for a, b in zip(p.sizes, ends, strict=True)]
        return pa.table({
            "chunk": pa.array(p.chunks, pa.int64()), "part": pa.array([rows["part"][0].as_py()] * len(spans), pa.int32()),
            "told": pa.array([_pack(told[s]) for s in spans], pa.binary()),
            "counts": pa.array([_pack(counts[s][told[s] & OWN > 0]) for s in spans], pa.binary()),
        })

    return run


def _told(texts: pa.Table, answers: pa.Table, k: int, parts: int):
    """A chunk's text, places and codes with what each place is told and the counts of owned ones."""
    text = _unpack(texts["text"][0].as_py())
    place, code, first, many, _ = _stretches(text, k, parts)
    answers = answers.sort_by("part")
    at = _spread(first, many)
    told, counts = np.empty(len(place), np.uint8), np.zeros(len(place), np.int64)
    if len(place):
        told[at] = np.concatenate([_unpack(x.as_py()) for x in answers["told"]])
        counts[at[told[at] & OWN > 0]] = np.concatenate([_unpack(x.as_py(), np.int64) for x in answers["counts"]])
    return text, place, code, told, counts


def _meet(held: DataFrame, k: int, parts: int, least: int | None, emit, schema: str) -> DataFrame:
    """``emit`` for each chunk with the answers it got."""
    answers = asked(held, k, parts).groupBy("part").applyInArrow(_answer(k, least), ANSWER)
    return held.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(emit, schema)


# ---------------------------------------------------------------- reads without rare k-mers


def without_rare(held: DataFrame, k: int, least: int = 2) -> DataFrame:
    """Chunks whose reads are cut at k-mers seen fewer than ``least`` times, which go."""
    parts = parts_for(held)

    def emit(texts: pa.Table, answers: pa.Table) -> pa.Table:
        text, place, _, told, _ = _told(texts, answers, k, parts)
        place = place[told > 0]
        first = np.flatnonzero(np.diff(place, prepend=-2) != 1)
        many = np.diff(np.append(first, len(place))) + k - 1
        out = np.full(int((many + 1).sum()) + 1, 10, np.uint8)
        mark = np.cumsum(many + 1) - (many + 1)
        out[mark[text[place[first] - 1] == 13]] = 13
        out[_spread(mark + 1, many)] = text[_spread(place[first], many)]
        return pa.table({"chunk": texts["chunk"], "sure": texts["sure"], "text": pa.array([_pack(out)], pa.binary())})

    return cut(_meet(held, k, parts, least, emit, "chunk long, sure boolean, text binary"))


# ---------------------------------------------------------------- units and links

PIECE = pa.schema([("head", pa.int64()), ("dst", pa.int64()), ("open", pa.bool_()), ("seq", pa.string()), ("coverage", pa.int64()), ("n", pa.int64())])


class _Pieces:
    """The pieces that a chunk's reads are cut in: ``first`` and ``last`` of their places, and how they meet."""

    def __init__(self, text: np.ndarray, place: np.ndarray, code: np.ndarray, told: np.ndarray, k: int):
        self.text, self.place, self.code, self.told, self.k = text, place, code, told, k
        on = np.zeros(len(place), bool)
        on[:-1] = place[1:] == place[:-1] + 1
        hard, soft = np.zeros(len(place), bool), np.zeros(len(place), bool)
        hard[:-1] = on[:-1] & (((told[:-1] & OUT | told[1:] & IN) > 0) | (code[1:] == code[:-1]))
        soft[:-1] = on[:-1] & ~hard[:-1] & ((told[:-1] & ENDS | told[1:] & STARTS) > 0)
        self.last = last = np.flatnonzero(~on | hard | soft)
        self.first = first = np.concatenate(([0], last[:-1] + 1)) if len(last) else last
        self.n, self.head = last - first + 1, code[first]
        self.hard, self.soft, self.on = hard[last], soft[last], on[last]
        # may go on: as it does here, or as a read's end leaves open
        self.goes = self.soft | ~self.on & (told[last] & ENDS > 0)
        came = np.concatenate(([False], self.soft[:-1])) if len(last) else self.goes
        self.after = np.concatenate(([False], self.on[:-1])) if len(last) else self.on
        self.came = came | ~self.after & (told[first] & STARTS > 0)
        self.open, self.own = self.goes | self.came, told[first] & OWN > 0

    def texts(self, which: np.ndarray) -> pa.Array:
        wide = self.n[which] + self.k - 1
        return _texts(self.text[_spread(self.place[self.first[which]], wide)], wide)

    def rows(self, schema: pa.Schema, which: np.ndarray, counts: np.ndarray, **more) -> pa.Table:
        n = self.n[which]
        return _rows(schema, head=self.head[which], seq=self.texts(which), coverage=n * counts[self.first[which]], n=n, **more)


def units_of(held: DataFrame, k: int, with_links: bool = True) -> tuple[DataFrame, DataFrame]:
    """``units``(head, seq, coverage, n) and ``links``(src, dst) of the reads in chunks; heads are k-mers as numbers."""
    parts = parts_for(held)

    def emit(texts: pa.Table, answers: pa.Table) -> pa.Table:
        text, place, code, told, counts = _told(texts, answers, k, parts)
        p = _Pieces(text, place, code, told, k)
        own = np.flatnonzero(p.own)
        pieces = p.rows(PIECE, own, counts, open=p.open[own])
        edge = np.flatnonzero((p.soft | p.hard if with_links else p.soft) & (told[p.last] & EDGE > 0))
        return pa.concat_tables([pieces, _rows(PIECE, head=p.head[edge], dst=p.head[edge + 1], open=p.soft[edge])])

    rows = cut(_meet(held, k, parts, None, emit, "head long, dst long, open boolean, seq string, coverage long, n long"))
    pieces, edges = rows.where("dst IS NULL"), rows.where("dst IS NOT NULL").select(F.col("head").alias("src"), "dst", "open")
    unit = ("head", "seq", "coverage", "n")
    whole, glued = glue(pieces.where("open").select(*unit), edges.where("open").select("src", "dst"), k)
    units = pieces.where("NOT open").select(*unit).union(whole).union(glued.select(*unit))
    return units, _renamed(edges.where("NOT open").select("src", "dst"), glued)


def _renamed(links: DataFrame, glued: DataFrame) -> DataFrame:
    """Links that leave the last piece of a joined unit leave the unit."""
    return links.join(glued.select(F.col("last").alias("src"), F.col("head").alias("unit")), "src", "left").select(F.coalesce("unit", "src").alias("src"), "dst")


def _chains(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [r for b in batches for r in b.to_pylist()]
        by = {r["head"]: r for r in rows}
        into = {r["next"] for r in rows if r["next"] is not None}
        out, done = [], set()

        def walk(at: int) -> list[dict]:
            path = []
            while at is not None and at not in done:
                done.add(at)
                path.append(by[at])
                at = by[at]["next"]
            return path

        for start in [h for h in by if h not in into] + list(by):
            if start in done:
                continue
            path = walk(start)
            seq = path[0]["seq"] + "".join(r["seq"][k - 1 :] for r in path[1:])
            n = sum(r["n"] for r in path)
            if start in into:  # a cycle begins at its smallest k-mer
                at = min(range(n), key=lambda i: seq[i : i + k])
                ring = seq[at:n] + seq[:at]
                seq = (ring * (k // n + 2))[: n + k - 1]
            out.append((int(seq[:k], BASE), seq, sum(r["coverage"] for r in path), n, path[-1]["head"]))
        if out:
            columns = zip(*out, strict=True)
            kinds = (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["head", "seq", "coverage", "n", "last"])

    return run


def _labels(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A number for each vertex that is that of its chain or cycle; links are one out and one in at most."""
    rows = [(b.column("src").to_numpy(), b.column("dst").to_numpy()) for b in batches]
    if not rows:
        return
    src, dst = (np.concatenate(x) for x in zip(*rows, strict=True))
    ids = np.unique(np.concatenate([src, dst]))
    root, low = np.arange(len(ids)), np.arange(len(ids))
    root[np.searchsorted(ids, dst)] = np.searchsorted(ids, src)
    before = root.copy()
    for _ in range(len(ids).bit_length() + 1):
        low, root = np.minimum(low, low[root]), root[root]
    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(ids[np.where(before[root] == root, root, low)])], names=["vid", "label"])


def _ends(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A label for each open vertex, from where it looks back to; who looks back to nobody is a first one."""
    rows = [[b.column(c).to_numpy(zero_copy_only=False) for c in ("vid", "up", "low", "open")] for b in batches]
    if not rows:
        return
    vid, up, least, open_ = (np.concatenate(x) for x in zip(*rows, strict=True))
    ids = np.unique(np.concatenate([vid, up]))
    at, back, low = np.searchsorted(ids, vid), np.arange(len(ids)), ids.copy()
    back[at], low[at] = np.searchsorted(ids, up), least
    first = np.ones(len(ids), bool)
    first[at] = False
    for _ in range(len(ids).bit_length() + 1):
        low, back = np.minimum(low, low[back]), back[back]
    label = np.where(first[back], ids[back], low)[at]
    yield pa.RecordBatch.from_arrays([pa.array(vid[open_]), pa.array(label[open_])], names=["vid", "label"])


def _chain_labels(soft: DataFrame) -> DataFrame:
    """What ``_labels`` gives, in rounds: each vertex looks twice as far back as in the round before, till its chain's
    first one is found.  Those that have found it ask no more, and the last few end in one task; cycles are left,
    whose smallest has been seen."""
    at = cut(soft.select(F.col("dst").alias("vid"), F.col("src").alias("up"), F.least("src", "dst").alias("low"), F.lit(True).alias("open")))
    found, open_, left, before, reach = at.where("false"), at, at.count(), 0, 1
    while left > FEW and (left != before or reach < left):  # a round ends some of any chain, so what stays is cycles
        beyond = open_.union(found).select(F.col("vid").alias("up"), F.col("up").alias("far"), F.col("low").alias("least"), F.col("open").alias("on"))
        look = open_.select("vid", "up", "low").join(beyond, "up", "left")
        nxt = cut(look.select("vid", F.coalesce("far", "up").alias("up"), F.least("low", "least").alias("low"), F.coalesce("on", F.lit(False)).alias("open")))
        open_, found = nxt.where("open"), found.union(nxt.where("NOT open"))
        left, before, reach = open_.count(), left, 2 * reach
    if left > FEW:
        rest = open_.select("vid", F.col("low").alias("label"))
    else:
        known = found.join(open_.select(F.col("up").alias("vid")).distinct(), "vid", "left_semi")
        rest = cut(open_.union(known).coalesce(1).mapInArrow(_ends, "vid long, label long"))
    label = found.select("vid", F.col("up").alias("label")).union(rest)
    first = soft.select(F.col("src").alias("vid")).join(soft.select(F.col("dst").alias("vid")), "vid", "left_anti")
    return label.union(first.select("vid", F.col("vid").alias("label")))


def _labelled(soft: DataFrame) -> DataFrame:
    """(head, label) of the pieces that soft links touch."""
    label = lambda: soft.coalesce(1).mapInArrow(_labels, "vid long, label long") if soft.count() <= FEW else _chain_labels(soft)
    return kept(lambda: (cut(label()),))[0].withColumnRenamed("vid", "head")


def _glued(rows: DataFrame, k: int) -> DataFrame:
    """Units (head, seq, coverage, n, last piece) of pieces with label and next one."""
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return cut(rows.repartition(parts, "label").mapInArrow(_chains(k), "head long, seq string, coverage long, n long, last long"))


def glue(pieces: DataFrame, soft: DataFrame, k: int) -> tuple[DataFrame, DataFrame]:
    """Pieces that no soft link touches, and units (head, seq, coverage, n, last piece) joined along soft links."""
    soft = cut(soft)
    label = _labelled(soft)
    glued = _glued(pieces.join(label, "head").join(soft.toDF("head", "next"), "head", "left"), k)
    return pieces.join(label, "head", "left_anti"), glued


def compact(units: DataFrame, links: DataFrame, gone: DataFrame, k: int) -> tuple[DataFrame, DataFrame]:
    """Units and links after the units of ``gone``(head) have gone: what no longer branches is joined.

    Units are gone over once, for those that go, stay and are joined.
    """
    (gone,) = kept(lambda: (cut(gone.select("head").distinct()),))
    links = cut(links.join(gone.toDF("src"), "src", "left_anti").join(gone.toDF("dst"), "dst", "left_anti").select("src", "dst"))
    one_out = links.groupBy("src").agg(F.count("*").alias("n"), F.min("dst").alias("dst")).where("n = 1").select("src", "dst")
    one_in = links.groupBy("dst").agg(F.count("*").alias("n")).where("n = 1").select("dst")
    only = cut(one_out.join(one_in, "dst").select("src", "dst"))
    rings = only.where("src = dst").join(units.where("n > 1").select(F.col("head").alias("src")), "src", "left_semi")
    soft = cut(only.where("src <> dst").union(rings.select("src", "dst")))
    named = _labelled(soft).join(soft.toDF("head", "next"), "head", "left").select("head", "label", "next", F.lit(True).alias("stays"))
    none = F.lit(None).cast("long")
    marks = named.union(gone.select("head", none, none, F.lit(False)))
    marked = cut(units.select("head", "seq", "coverage", "n").join(marks, "head", "left").where("coalesce(stays, true)").drop("stays"))
    glued = _glued(marked.where("label IS NOT NULL"), k)
    whole = marked.where("label IS NULL").select("head", "seq", "coverage", "n")
    return whole.union(glued.drop("last")), cut(_renamed(links.join(soft, ["src", "dst"], "left_anti"), glued))


def _components(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The smallest vertex of its component for each vertex that links touch."""
    rows = [(b.column("vid").to_numpy(), b.column("near").to_numpy()) for b in batches]
    if not rows:
        return
    ids, n = np.unique(np.concatenate([x for r in zip(*rows, strict=True) for x in r]), return_inverse=True)
    a, b = n[: len(n) // 2], n[len(n) // 2 :]
    low = np.arange(len(ids))
    while (low[a] != low[b]).any():
        most, least = np.maximum(low[a], low[b]), np.minimum(low[a], low[b])
        np.minimum.at(low, most, least)
        while (low != low[low]).any():
            low = low[low]
    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(ids[low])], names=["vid", "label"])


def without_small(units: DataFrame, links: DataFrame, least: int) -> DataFrame:
    """Units of components with ``least`` k-mers at least.

    A unit that has so many together with those it is linked to stays, and so do these.  Components are sought among
    the other units alone, and stay if one of them is linked to a unit that stays.
    """
    near = links.where("src <> dst").select(F.explode(F.array(F.struct(F.col("src").alias("vid"), F.col("dst").alias("near")), F.struct(F.col("dst").alias("vid"), F.col("src").alias("near")))).alias("x"))
    near = cut(near.select("x.*").distinct())
    size = units.select("head", "n")
    around = near.join(size.toDF("near", "n"), "near").groupBy(F.col("vid").alias("head")).agg(F.sum("n").alias("more"))
    own = cut(size.join(around, "head", "left").select("head", "n", (F.col("n") + F.coalesce("more", F.lit(0)) >= least).alias("sure"), F.col("more").isNotNull().alias("linked")))
    beside = near.join(own.where("sure").select(F.col("head").alias("near")), "near").select(F.col("vid").alias("head")).distinct()
    # of those linked, all but the sure ones and what is beside these
    doubt = cut(own.where("linked AND NOT sure").select("head", "n").join(beside, "head", "left_anti"))
    met = cut(near.join(doubt.select(F.col("head").alias("vid")), "vid").join(doubt.select(F.col("head").alias("near"), F.lit(True).alias("too")), "near", "left").select("vid", "near", F.coalesce("too", F.lit(False)).alias("inner")))
    inner = met.where("inner").select("vid", "near")
    if inner.count() <= 2 * FEW:
        label = inner.where("vid < near").coalesce(1).mapInArrow(_components, "vid long, label long")
    else:
        label = min_label(inner.where("vid < near").toDF("src", "dst"), doubt.select(F.col("head").alias("vid")))
    told = doubt.join(label.withColumnRenamed("vid", "head"), "head", "left").join(met.where("NOT inner").select(F.col("vid").alias("head"), F.lit(True).alias("held")).distinct(), "head", "left")
    told = cut(told.select("head", "n", F.coalesce("label", "head").alias("label"), F.coalesce("held", F.lit(False)).alias("held")))
    big = told.groupBy("label").agg(F.sum("n").alias("all"), F.max("held").alias("held")).where(F.col("held") | (F.col("all") >= least)).select("label")
    small = told.join(big, "label", "left_anti").select("head").union(own.where("NOT linked AND NOT sure").select("head"))
    return units.join(small, "head", "left_anti")


# ---------------------------------------------------------------- units less those that a step takes away

MARKED = pa.schema([("text", pa.binary()), ("told", pa.binary()), ("counts", pa.binary()), ("head", pa.int64()), ("dst", pa.int64()), ("seq", pa.string()), ("coverage", pa.int64()), ("n", pa.int64()), ("left", pa.int64()), ("right", pa.int64()), ("slot", pa.int64()), ("asked", pa.binary())])
NEAR = pa.schema([("head", pa.int64()), ("dst", pa.int64()), ("seq", pa.string()), ("coverage", pa.int64()), ("n", pa.int64()), ("doubt", pa.bool_())])


def _sides(p: _Pieces) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of whole units: whether anything comes before and after them, and whether just one does."""
    told_in, told_out = p.told[p.first], p.told[p.last]
    before, after = p.after | (told_in & (IN | STARTS) > 0), p.on | (told_out & (OUT | ENDS) > 0)
    return before, after, before & (told_in & IN == 0), after & (told_out & OUT == 0)


def tips(p: _Pieces) -> tuple[np.ndarray, None]:
    """Short units that end dead on one side."""
    before, after, _, _ = _sides(p)
    return (p.n <= p.k) & (before != after), None


def bridges(most: int = 16, long: int = 40) -> Callable:
    """Short units that have units on both sides, of which no short one is seen here."""

    def of(p: _Pieces) -> tuple[np.ndarray, None]:
        before, after, _, _ = _sides(p)
        brief = p.n + p.k - 1 < long
        spoilt = np.zeros(len(p.n), bool)
        spoilt[1:] |= p.after[1:] & (brief & ~p.came)[:-1]
        spoilt[:-1] |= p.on[:-1] & (brief & ~p.goes)[1:]
        return (p.n + p.k - 1 <= most) & before & after & ~spoilt, None

    return of


def arms(p: _Pieces) -> tuple[np.ndarray, np.ndarray]:
    """Units with one before and one after them, and a number made of the k-mers next to them."""
    _, _, one_in, one_out = _sides(p)
    may = one_in & one_out & ~p.open
    around = np.zeros(len(p.n), np.uint64)
    at = np.flatnonzero(may)
    around[at] = p.code[p.first[at] - 1].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) ^ (p.code[p.last[at] + 1] + 1).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
    return may, around.view(np.int64)


def _bits(p: _Pieces, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Places in the filter of the k - 1 letters at which a piece meets those before it, and those after it."""
    mix = lambda x: (((x + 1).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - size)).astype(np.int64)
    return mix(p.head // BASE), mix(p.code[p.last] % BASE ** (p.k - 1))


def _filter(bits: DataFrame, size: int) -> np.ndarray:
    """All of ``bits``(bit) set, in a table whose size does not depend on how many there are."""
    at = F.col("bit") + 1
    rows = bits.groupBy(F.bitmap_bucket_number(at).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bitmap"))
    out = np.zeros(max(1 << size >> 3, 4096), np.uint8)
    for r in rows.collect():
        out[(r.bucket - 1) * 4096 : r.bucket * 4096] = np.frombuffer(r.bitmap, np.uint8)
    return out


#: A unit that goes only if another has the same key, and where it meets others.
ASK = np.dtype([("key", np.uint64), ("left", np.uint32), ("right", np.uint32)])


def _dealt(key: np.ndarray, left: np.ndarray, right: np.ndarray, slots: int) -> pa.Table:
    """A chunk's asks in a packed row for each slot that they are dealt to by key."""
    asks = np.empty(len(key), ASK)
    asks["key"], asks["left"], asks["right"] = key.view(np.uint64), left, right
    slot = ((asks["key"] * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(32)) % np.uint64(slots)
    order = np.argsort(slot, kind="stable")
    asks, slot = asks[order], slot[order]
    first = np.flatnonzero(np.diff(slot.astype(np.int64), prepend=-1))
    packed = [_pack(x) for x in np.split(asks, first[1:])][: len(first)]
    return _rows(MARKED, slot=slot[first].astype(np.int64), asked=pa.array(packed, pa.binary()))


def _twice(rows: pa.Table) -> pa.Table:
    """Where units meet others whose key another unit has too."""
    asks = np.concatenate([_unpack(x.as_py(), ASK) for x in rows["asked"]])
    asks = asks[np.argsort(asks["key"])]
    same = asks["key"][1:] == asks["key"][:-1]
    asks = asks[np.append(False, same) | np.append(same, False)]
    return pa.table({"left": pa.array(asks["left"], pa.int64()), "right": pa.array(asks["right"], pa.int64())})


def cleaned(held: DataFrame, k: int, doubtful: Callable, step: Callable[[DataFrame, DataFrame], DataFrame], size: int = FILTER) -> DataFrame:
    """``step(*units_of(held, k))`` for steps that take units away by what else meets at their two ends.

    ``doubtful`` tells by a chunk alone which units may go, a few of all; with a number, only if another has the same.
    All units that meet where one of these or of the open pieces ends come to ``step`` with all their links there;
    the other units stay, and are made from the chunks where the result is written.  Where units meet is looked up
    in a filter of a fixed size, which lets more come to ``step`` than need be, and all if it is full.
    """
    parts, spark, unit = parts_for(held), held.sparkSession, ("head", "seq", "coverage", "n")

    def emit(texts: pa.Table, answers: pa.Table) -> pa.Table:
        text, place, code, told, counts = _told(texts, answers, k, parts)
        p = _Pieces(text, place, code, told, k)
        may, key = doubtful(p)
        left, right = _bits(p, size)
        open_, may = np.flatnonzero(p.own & p.open), np.flatnonzero(p.own & ~p.open & may)
        soft = np.flatnonzero(p.soft & (told[p.last] & EDGE > 0))
        asks = [_rows(MARKED, left=left[open_], right=right[open_]), _rows(MARKED, left=left[may], right=right[may]) if key is None else _dealt(key[may], left[may], right[may], parts)]
        block = _rows(MARKED, text=[texts["text"][0].as_py()], told=[_pack(told)], counts=[_pack(counts[told & OWN > 0])])
        return pa.concat_tables([block, p.rows(MARKED, open_, counts), _rows(MARKED, head=p.head[soft], dst=p.head[soft + 1]), *asks])

    kinds = {pa.binary(): "binary", pa.int64(): "long", pa.string(): "string", pa.bool_(): "boolean"}
    told_as = lambda schema: ", ".join(f"{f.name} {kinds[f.type]}" for f in schema)
    marked = cut(_meet(held, k, parts, None, emit, told_as(MARKED)))
    pool = ThreadPoolExecutor(1)  # what is joined and what is looked up don't wait for each other
    pieces = marked.where("head IS NOT NULL")
    joined = pool.submit(glue, pieces.where("dst IS NULL").select(*unit), pieces.where("dst IS NOT NULL").select(F.col("head").alias("src"), "dst"), k)
    asks = marked.where("left IS NOT NULL").select("left", "right")
    twice = marked.where("slot IS NOT NULL").select("slot", "asked").groupBy("slot").applyInArrow(_twice, "left long, right long")
    known = spark.sparkContext.broadcast(_filter(asks.union(twice).select(F.explode(F.array("left", "right")).alias("bit")), size))

    def blocks(make: Callable[[_Pieces, np.ndarray, np.ndarray, np.ndarray], pa.Table]):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            bits = known.value
            for batch in batches:
                for packed, told, counts in zip(*(batch.column(c).to_pylist() for c in ("text", "told", "counts")), strict=True):
                    text, told = _unpack(packed), _unpack(told)
                    place, code = _places(text, k)
                    many = np.zeros(len(place), np.int64)
                    many[told & OWN > 0] = _unpack(counts, np.int64)
                    p = _Pieces(text, place, code, told, k)
                    left, right = ((bits[at >> 3] >> (at & 7)) & 1 > 0 for at in _bits(p, size))
                    yield from make(p, many, left, right).to_batches()

        return run

    def near(p: _Pieces, counts: np.ndarray, left: np.ndarray, right: np.ndarray) -> pa.Table:
        own = np.flatnonzero(p.own & ~p.open & (left | right))
        edge = np.flatnonzero(p.hard & right & (p.told[p.last] & EDGE > 0))
        return pa.concat_tables([p.rows(NEAR, own, counts, doubt=(doubtful(p)[0] & left & right)[own]), _rows(NEAR, head=p.head[edge], dst=p.head[edge + 1])])

    def rest(p: _Pieces, counts: np.ndarray, left: np.ndarray, right: np.ndarray) -> pa.Table:
        return p.rows(pa.schema(list(NEAR)[:1] + list(NEAR)[2:5]), np.flatnonzero(p.own & ~p.open & ~left & ~right), counts)

    block = marked.where("text IS NOT NULL").select("text", "told", "counts")
    found = cut(block.mapInArrow(blocks(near), told_as(NEAR)))
    whole, glued = joined.result()
    held_links = pool.submit(cut, _renamed(found.where("dst IS NOT NULL").select(F.col("head").alias("src"), "dst"), glued))
    units = cut(found.where("dst IS NULL").select(*unit, "doubt").union(whole.union(glued.select(*unit)).withColumn("doubt", F.lit(True))))
    links = held_links.result()
    pool.shutdown()
    stay = units.where("NOT doubt").select(*unit).union(step(units, links).where("doubt").select(*unit))
    return block.mapInArrow(blocks(rest), "head long, seq string, coverage long, n long").union(stay)


# ---------------------------------------------------------------- k-mers of parts that are not small

NODE = pa.schema([("kmer", pa.string()), ("coverage", pa.int64())])
DOUBT = pa.schema([("vid", pa.int64()), ("dst", pa.int64()), ("coverage", pa.int64()), ("held", pa.bool_())])


def _names(code: np.ndarray, k: int) -> pa.Array:
    out = np.empty((len(code), k), np.uint8)
    for j in range(k - 1, -1, -1):
        code, rest = np.divmod(code, BASE)
        out[:, j] = LETTER[rest]
    return _texts(out.ravel(), np.full(len(out), k))


def big_components(read: DataFrame, k: int, least: int) -> DataFrame:
    """(kmer, coverage) of components with at least ``least`` k-mers.

    The k-mers of a read are in one component, so all of a read with ``least`` different ones stay.  Components are
    found among the k-mers of the other reads alone.
    """
    held = chunks(read, k, least)
    parts = parts_for(held)
    told = cut(asked(held, k, parts))

    def sure_of(p: _Part) -> np.ndarray:
        return np.repeat(np.array(p.sure, bool), p.sizes)[p.order]

    def nodes(rows: pa.Table) -> pa.Table:
        p = _Part(rows, k)
        sure = np.logical_or.reduceat(sure_of(p), p.heads)
        return pa.table([_names(p.code[sure], k), pa.array(p.count[sure], pa.int64())], schema=NODE)

    def doubts(rows: pa.Table) -> pa.Table:
        p = _Part(rows, k)
        sure = sure_of(p)
        held, asks = np.logical_or.reduceat(sure, p.heads), np.logical_or.reduceat(~sure, p.heads)
        edge = np.flatnonzero(~sure & (p.after < BASE))
        src = np.repeat(p.code, p.many)[edge]
        return pa.concat_tables([
            _rows(DOUBT, vid=p.code[asks], coverage=p.count[asks], held=held[asks]),
            _rows(DOUBT, vid=src, dst=src % BASE ** (k - 1) * BASE + p.after[edge]),
        ])

    doubt = cut(told.join(told.where("NOT sure").select("part").distinct(), "part", "left_semi").groupBy("part").applyInArrow(doubts, "vid long, dst long, coverage long, held boolean"))
    ids = doubt.where("dst IS NULL").select("vid", "coverage", "held")
    label = min_label(doubt.where("dst IS NOT NULL").select(F.col("vid").alias("src"), "dst"), ids.select("vid"))
    label = cut(label.join(ids, "vid"))
    big = label.groupBy("label").agg(F.count("*").alias("n"), F.max("held").alias("held")).where(F.col("held") | (F.col("n") >= least)).select("label")
    rest = label.where("NOT held").join(big, "label", "left_semi").select("vid", "coverage")

    def named(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([_names(b.column("vid").to_numpy(), k), b.column("coverage")], schema=NODE)

    return told.groupBy("part").applyInArrow(nodes, "kmer string, coverage long").union(rest.mapInArrow(named, "kmer string, coverage long"))
