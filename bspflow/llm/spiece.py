"""SentencePiece segmentations sampled without replacement, and decoding.

A text is a lattice of pieces; a segmentation's probability is the product of its piece weights over the sum for all
segmentations.  No piece goes on past a space, so the lattice is a chain of word lattices: one backward pass per
distinct word of a batch gives, at each place, the probabilities of the pieces that may come next.

Gumbel top-k: every segmentation has its log-probability plus Gumbel noise; the k largest are k draws without
replacement.  A best-first search finds them without listing the rest.  The mass of a set of segmentations gives the
law of its largest perturbed value, so the first path is an ordinary draw, carrying the largest value of all.  Each
place where it chose a piece leaves one queue entry: the segmentations that agree up to there and go on otherwise,
with a value drawn below the path's.  The queue's best entry gives the next path, which leaves entries in turn.  The
value left on top after k paths is the threshold of the inclusion scores: a segmentation of log-probability p would
have been among the k with probability 1 - exp(-exp(p - threshold)).

Weights: a unigram model's piece scores are log-probabilities and are used as they are.  A model of merge ranks (BPE)
has no probabilities; its pieces weigh 1 / (1 + rank).  ``sharpness`` multiplies log weights.  A character without a
piece of its own is its UTF-8 bytes' pieces.  Random numbers are hashes of (seed, row key, path, place), so a row's
samples don't depend on where or with what it is processed.

Defined cases: null or empty text has one empty segmentation of probability 1; a text with fewer than k
segmentations gives all of them, with inclusion 1; a literal U+2581 is coded as bytes so that decoding is exact; rows
with equal key and text get equal samples; null keys are a key like any other; empty tables give empty results;
extra columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import mix64, plain, text_slices

SPACE = "▁"
#: Bytes of text sampled at a time, and words whose lattices a worker keeps from one slice to the next.
SLICE, KEPT = 1 << 18, 1 << 13
#: Log weight of a character that is coded as bytes; it has no alternative, so only its own row's scale shifts.
BYTES_WEIGHT = -20.0


class Pieces:
    """A vocabulary as arrays: a trie of transitions, weights, and what each piece decodes to."""

    def __init__(self, model: bytes, sharpness: float = 1.0):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_proto=model)
        n = sp.get_piece_size()
        scores = np.array([sp.get_score(i) for i in range(n)])
        normal = [i for i in range(n) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
        ranked = all(float(scores[i]).is_integer() for i in normal)
        weights = -np.log1p(-np.minimum(scores, 0)) if ranked else scores
        self.bytes_first = next((i for i in range(n) if sp.is_byte(i)), None)
        pieces = {sp.id_to_piece(i): i for i in normal}
        self.text = [b""] * n
        for p, i in pieces.items():
            self.text[i] = p.replace(SPACE, " ").encode()
        if self.bytes_first is not None:
            for b in range(256):
                self.text[self.bytes_first + b] = bytes([b])
        chars = sorted({c for p in pieces for c in p})
        self.char_of = np.zeros(0x110000, np.int32)
        for k, c in enumerate(chars):
            self.char_of[ord(" " if c == SPACE else c)] = k + 1
        self.char_of[ord(SPACE)] = 0
        self.alphabet = len(chars) + 1
        number = {c: k + 1 for k, c in enumerate(chars)}
        kids: dict[int, int] = {}
        ends, states = {}, 1
        for p, i in pieces.items():
            at = 0
            for c in p:
                key = at * self.alphabet + number[c]
                if key not in kids:
                    kids[key] = states
                    states += 1
                at = kids[key]
            ends[at] = i
        #: transitions of the root by character, the others by a search among sorted keys
        self.root = np.full(self.alphabet, -1, np.int32)
        for key in [k for k in kids if k < self.alphabet]:
            self.root[key] = kids.pop(key)
        keys = np.array(sorted(kids), np.int64)
        self.shift = np.uint64(64 - max(4, 3 + len(keys).bit_length()))
        self.keys = np.full((1 << 64 - int(self.shift)) + 64, -1, np.int64)
        self.next = np.zeros(len(self.keys), np.int32)
        for key, slot in zip(keys.tolist(), self._slot(keys).tolist(), strict=True):
            while self.keys[slot] != -1:
                slot += 1
            self.keys[slot], self.next[slot] = key, kids[key]
        self.ends = np.full(states, -1, np.int32)
        for s, i in ends.items():
            self.ends[s] = i
        self.weights = weights * sharpness
        lengths = np.array([len(t) for t in self.text], np.int64)
        self.blob, self.sizes, self.offsets = np.frombuffer(b"".join(self.text), np.uint8), lengths, np.cumsum(lengths) - lengths
        alone = not any("\n" in p and len(p) > 1 for p in pieces)
        self.unit = re.compile(" *[^ \n]+| *\n| +" if alone else " *[^ ]+| +")

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def step(self, key: np.ndarray) -> np.ndarray:
        """The state after each transition, -1 where there is none."""
        slot = self._slot(key)
        there = self.keys[slot]
        out = np.where(there == key, self.next[slot], np.int32(-1))
        open_ = np.flatnonzero((there != key) & (there != -1))
        while len(open_):
            slot[open_] += 1
            there = self.keys[slot[open_]]
            hit = there == key[open_]
            out[open_[hit]] = self.next[slot[open_[hit]]]
            open_ = open_[~hit & (there != -1)]
        return out

    def raw(self, ids: np.ndarray) -> np.ndarray:
        """The bytes of piece numbers one after another."""
        many = self.sizes[ids]
        ends = np.cumsum(many)
        total = int(ends[-1]) if len(ends) else 0
        return self.blob[np.repeat(self.offsets[ids] - (ends - many), many) + np.arange(total)]

    def decode(self, ids: list[int]) -> str:
        """The text of piece numbers; the space put before a text is taken off again."""
        raw = b"".join(map(self.text.__getitem__, ids)).decode("utf-8", "replace")
        return raw[1:] if raw[:1] == " " else raw


class Lattice:
    """The joined lattices of distinct units (words with the spaces before them), after those of ``base`` if given."""

    def __init__(self, pieces: Pieces, units: list[str], base: Lattice | None = None):
        text = np.frombuffer("".join(units).encode("utf-32-le", "surrogatepass"), np.uint32)
        self.lengths = np.fromiter(map(len, units), np.int64, len(units))
        self.first = np.cumsum(self.lengths) - self.lengths
        n = len(text)
        left = (np.repeat(self.first + self.lengths, self.lengths) - np.arange(n)).astype(np.int32)
        char = pieces.char_of[text]
        start, length, piece = [], [], []
        at, state, step = np.arange(n, dtype=np.int32), np.zeros(n, np.int32), 0
        single = np.zeros(n, bool)
        while len(at):
            if step == 0:
                state = pieces.root[char]
                ok = state >= 0
                at, state = at[ok], state[ok]
            else:
                state = pieces.step(state.astype(np.int64) * pieces.alphabet + char[at + step])
                ok = state >= 0
                at, state = at[ok], state[ok]
            end = pieces.ends[state]
            done = end >= 0
            start.append(at[done])
            length.append(np.full(int(done.sum()), step + 1, np.int32))
            piece.append(end[done])
            if step == 0:
                single[at[done]] = True
            step += 1
            more = left[at] > step
            at, state = at[more], state[more]
        alone = np.flatnonzero(~single).astype(np.int32)
        start.append(alone)
        length.append(np.ones(len(alone), np.int32))
        # one byte is one piece; more are looked up below
        code = text[alone].astype(np.int64)
        piece.append(np.where((code < 128) & (pieces.bytes_first is not None), code + (pieces.bytes_first or 0), -1).astype(np.int32))
        byte = len(alone)
        start, length, piece = map(np.concatenate, (start, length, piece))
        weight = pieces.weights[piece]
        weight[len(piece) - byte :] = BYTES_WEIGHT
        order = np.argsort(start, kind="stable")
        start, self.length, piece, weight = start[order], length[order], piece[order], weight[order]
        self.group = np.concatenate(([0], np.cumsum(np.bincount(start, minlength=n)))).astype(np.int32)
        # backward sums, for all units at once, by how far a place is from its unit's end
        total = np.zeros(n + 1)
        far = left[start]
        by = np.argsort(far.astype(np.int16) if n and left.max() < 1 << 15 else far, kind="stable")
        cuts = np.flatnonzero(np.diff(far[by])) + 1
        ends_here = far == self.length
        target = start + self.length
        # places one past a unit's end add nothing: they point to the spare last sum
        target[ends_here] = n
        for e in np.split(by, cuts):
            s = start[e]
            heads = np.flatnonzero(np.concatenate(([True], s[1:] != s[:-1])))
            total[s[heads]] = np.logaddexp.reduceat(weight[e] + total[target[e]], heads) if len(e) else 0.0
        weight += total[target]
        weight -= total[start]
        self.log_p = weight
        p = np.exp(weight)
        sums = np.cumsum(p)
        many = np.diff(self.group)
        heads = self.group[:-1]
        self.upto = sums - np.repeat(sums[heads] - p[heads], many)
        self.upto[self.group[1:] - 1] = 2.0
        only = np.repeat(many == 1, many)
        self.log_p[only] = 0.0
        np.subtract(1.0, p, out=p)
        np.maximum(p, 1e-300, out=p)
        np.log(p, out=p)
        p[only] = -np.inf
        self.log_other = p
        self.ends_here, self.start = ends_here, start
        # piece numbers of each edge: one, or a character's bytes
        many = np.ones(len(start), np.int64)
        flat = piece
        raw = np.flatnonzero(piece < 0)
        if len(raw):
            coded = [chr(text[start[e]]).encode("utf-8", "surrogatepass") for e in raw.tolist()]
            many[raw] = [len(c) for c in coded]
            flat = np.repeat(piece, many)
            flat[flat < 0] = np.frombuffer(b"".join(coded), np.uint8).astype(np.int64) + (pieces.bytes_first or 0)
        self.many, self.flat, self.at = many, flat, np.cumsum(many) - many
        self.plain = not len(raw)
        self.room: dict[str, np.ndarray] = {}
        if base is not None:
            self._follow(base)

    def _follow(self, base: Lattice) -> None:
        """Number places and edges on from those of ``base``; the next lattice after the same base takes this one's room."""
        places, edges = len(base.group) - 1, len(base.start)
        self.first, self.start, self.at, self.group = self.first + places, self.start + places, self.at + len(base.flat), self.group[1:] + edges
        # the base stays in front of room that every slice writes its own into, so it is not copied for each
        for name in ("lengths", "first", "start", "length", "log_p", "upto", "log_other", "ends_here", "many", "flat", "at", "group"):
            held, own = getattr(base, name), getattr(self, name)
            a, b = len(held), len(held) + len(own)
            room = base.room.get(name)
            if room is None or len(room) < b:
                room = base.room[name] = np.empty(b + b // 4, held.dtype)
                room[:a] = held
            room[a:b] = own
            setattr(self, name, room[:b])
        self.plain = self.plain and base.plain

    def walk(self, occurrence: np.ndarray, place: np.ndarray, draw) -> tuple[np.ndarray, np.ndarray]:
        """Ordinary draws from the given places to the ends of their units: (occurrence, edge), in text order."""
        who, edges, live = [], [], np.arange(len(occurrence))
        place = place.copy()
        while len(live):
            u = draw(live, place[live])
            e = self.group[place[live]]
            go = np.arange(len(live))
            while len(go):
                go = go[u[go] >= self.upto[e[go]]]
                e[go] += 1
            who.append(occurrence[live])
            edges.append(e)
            place[live] += self.length[e]
            live = live[~self.ends_here[e]]
        if not who:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        who, edges = np.concatenate(who), np.concatenate(edges)
        order = np.argsort(who, kind="stable")
        return who[order], edges[order]

    def ids(self, edges: np.ndarray) -> np.ndarray:
        if self.plain:
            return self.flat[edges]
        many = self.many[edges]
        inside = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
        return self.flat[np.repeat(self.at[edges], many) + inside]


def _uniform(words: np.ndarray) -> np.ndarray:
    """Uniforms in (0, 1) from hashed words."""
    return ((mix64(words) >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53


class _Path:
    """One segmentation of a text: its edges and units, and the queue entries it left."""

    __slots__ = ("edges", "units", "value", "log_p", "start", "entries", "places", "before", "barred")

    def __init__(self, edges, units, value, lattice, start, before, barred, rest, noise):
        self.edges, self.units, self.value, self.start, self.barred = edges, units, value, start, barred
        tail = edges[start:]
        sums = np.cumsum(lattice.log_p[tail])
        self.log_p = before + (sums[-1] if len(sums) else 0.0)
        # noise of 53 bits lies between -3.7 and 37.5: what is further below the best mass can't be the best entry,
        # and masses only fall along the path
        far = len(tail)
        head = lattice.log_other[tail[:64]]
        best = (before + head[1:] + sums[: len(head)][:-1]).max(initial=before + head[0] if rest is None and len(head) else -np.inf)
        if best > -np.inf:
            far = 1 + int(np.searchsorted(-sums, before - min(best, value) + 42.0))
            tail = tail[:far]
        #: log mass of the prefix before each place from ``start`` on
        self.before = np.empty(len(tail))
        self.before[:1] = before
        np.add(sums[: len(tail)][:-1], before, out=self.before[1:])
        mass = self.before + lattice.log_other[tail]
        if rest is not None:
            mass[0] = rest
        self.places = np.flatnonzero(mass > max(min(mass.max(initial=-np.inf), value) - 42.0, -1e300))
        mass = mass[self.places]
        with np.errstate(over="ignore"):
            self.entries = mass - np.log(np.exp(np.minimum(mass - value, 700.0)) - np.log(noise(units[start:][self.places], tail[self.places])))


class Kept:
    """Lattices of words that recur, numbered from -1 down: built once and put before those of every slice."""

    def __init__(self, pieces: Pieces, texts: list[str | None]):
        often = Counter(w for t in texts if t and _single(t) for w in t.split(" "))
        words = [w for w, n in often.most_common(KEPT) if n > 1]
        self.numbers = {w: -1 - i for i, w in enumerate(words)}
        self.lattice = Lattice(pieces, [f" {w}" for w in words]) if words else None


def _single(text: str) -> bool:
    """Whether the words of a text stand one space apart."""
    return not ("  " in text or text[0] == " " or text[-1] == " ")


def sample_batch(pieces: Pieces, keys: list, texts: list[str | None], k: int, seed: int, kept: Kept | None = None) -> list[list[tuple[np.ndarray, float, float, float]]]:
    """For each text up to k of (piece numbers, log-probability, perturbed value, inclusion), best value first."""
    # words of texts with single spaces are numbered without the space before them, from -1 down
    known: dict[str, int] = defaultdict(lambda: len(known))
    spaced: dict[str, int] = defaultdict(lambda: -1 - len(spaced))
    base = kept.lattice if kept else None
    if base is not None:
        spaced.update(kept.numbers)
    n_base = len(spaced)
    unit_of, counts = [], []
    for t in texts:
        if t and _single(t):
            units, number = t.split(" "), spaced
        else:
            units, number = pieces.unit.findall(f" {t}") if t else (), known
        counts.append(len(units))
        unit_of.extend(map(number.__getitem__, units))
    out: list[list[tuple[np.ndarray, float, float, float]]] = [[] for _ in texts]
    counts = np.array(counts, np.int64)
    ends = np.cumsum(counts)
    unit_of = np.array(unit_of, np.int64)
    # kept words come first, then units with their spaces, then the slice's other words
    np.copyto(unit_of, np.where(unit_of < 0, np.where(unit_of >= -n_base, -1 - unit_of, len(known) - 1 - unit_of), n_base + unit_of))
    row_key = mix64(np.array([seed ^ (hash_of(x) & (1 << 63) - 1) for x in keys], np.uint64))
    for i, t in enumerate(texts):
        if not t:
            out[i] = [(np.zeros(0, np.int64), 0.0, 0.0, 1.0)]
    if not len(unit_of):
        return out
    units = [*known, *(f" {w}" for w in islice(spaced, n_base, None))]
    lattice = Lattice(pieces, units, base) if units else base
    doc_of = np.repeat(np.arange(len(texts)), counts)
    width = lattice.lengths[unit_of]
    upto = np.concatenate(([0], np.cumsum(width)))
    inside = upto[:-1] - upto[ends - counts][doc_of]
    begin = lattice.first[unit_of]

    def stream(number: int, doc: np.ndarray, place: np.ndarray) -> np.ndarray:
        return _uniform(row_key[doc] + (np.uint64(number) << np.uint64(40)) + place.astype(np.uint64))

    def walk(path: int, occurrence: np.ndarray, place: np.ndarray):
        def draw(live, at):
            o = occurrence[live]
            return stream(2 * path, doc_of[o], inside[o] + at - begin[o])

        return lattice.walk(occurrence, place, draw)

    def noise(path: int, doc: int):
        def at(units: np.ndarray, edges: np.ndarray) -> np.ndarray:
            place = inside[units] + lattice.start[edges] - begin[units]
            return stream(2 * path + 1, np.full(len(units), doc), place)

        return at

    live = [i for i, c in enumerate(counts) if c]
    who, edges = walk(0, np.arange(len(unit_of)), begin)
    cut = np.searchsorted(who, ends - counts), np.searchsorted(who, ends)
    tops = -np.log(-np.log(stream(1 << 12, np.arange(len(texts)), np.zeros(len(texts), np.int64))))
    paths: dict[int, list[_Path]] = {}
    for i in live:
        a, b = cut[0][i], cut[1][i]
        paths[i] = [_Path(edges[a:b], who[a:b], float(tops[i]), lattice, 0, 0.0, None, None, noise(0, i))]
    left: dict[int, float] = {}
    for r in range(1, k + 1):
        chosen = {}
        for i in live:
            best, of, at = -np.inf, None, 0
            for path in paths[i]:
                j = int(path.entries.argmax()) if len(path.entries) else 0
                if len(path.entries) and path.entries[j] > best:
                    best, of, at = float(path.entries[j]), path, j
            left[i] = best
            if of is not None:
                chosen[i] = (of, at, best)
        if r == k or not chosen:
            break
        live = list(chosen)
        start_o, start_p, new_edge = [], [], {}
        for i, (path, entry, _) in chosen.items():
            at = int(path.places[entry])
            t = path.start + at
            o, old = int(path.units[t]), int(path.edges[t])
            place = int(lattice.start[old])
            barred = {old} | (path.barred if at == 0 and path.barred else set())
            group = [e for e in range(int(lattice.group[place]), int(lattice.group[place + 1])) if e not in barred]
            p = np.exp(lattice.log_p[group])
            u = float(stream(2 * r, np.array([i]), np.array([inside[o] + place - begin[o]]))[0]) * p.sum()
            pick = min(int(np.searchsorted(np.cumsum(p), u, side="right")), len(group) - 1)
            rest = p.sum() - p[pick] if len(group) > 1 else 0.0
            new_edge[i] = (group[pick], barred, float(path.before[at]), rest)
            later = np.arange(o + 1, ends[i])
            if not lattice.ends_here[group[pick]]:
                start_o.append(np.array([o]))
                start_p.append(np.array([place + lattice.length[group[pick]]]))
            start_o.append(later)
            start_p.append(begin[later])
        who, edges = walk(r, np.concatenate(start_o), np.concatenate(start_p))
        firsts, lasts = np.searchsorted(who, ends - counts), np.searchsorted(who, ends)
        for i, (path, entry, value) in chosen.items():
            t = path.start + int(path.places[entry])
            edge, barred, before, rest = new_edge[i]
            full = np.concatenate((path.edges[:t], [edge], edges[firsts[i] : lasts[i]]))
            units = np.concatenate((path.units[: t + 1], who[firsts[i] : lasts[i]]))
            path.entries[entry] = -np.inf
            rest = before + np.log(rest) if rest > 1e-15 else -np.inf
            paths[i].append(_Path(full, units, value, lattice, t, before, barred, rest, noise(r, i)))
    for i, found in paths.items():
        bound = left.get(i, -np.inf)
        for path in found:
            inclusion = 1.0 if bound == -np.inf else float(-np.expm1(-np.exp(min(path.log_p - bound, 50.0))))
            out[i].append((lattice.ids(path.edges), float(path.log_p), path.value, inclusion))
    return out


def hash_of(key) -> int:
    """A number of a row key, the same in every process."""
    import xxhash

    return xxhash.xxh64_intdigest(repr(key).encode(), 5)


def _sample_rows(model: bytes, k: int, seed: int, sharpness: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces, kept = Pieces(model, sharpness), None
        for batch in batches:
            for part in text_slices(batch, budget=SLICE):
                keys, texts = part.column("doc_id").to_pylist(), part.column("text").to_pylist()
                if kept is None:
                    first = next(text_slices(batch, budget=8 * SLICE))
                    kept = Kept(pieces, first.column("text").to_pylist() if first.nbytes < 16 * SLICE else texts)
                found = sample_batch(pieces, keys, texts, k, seed, kept)
                row = [i for i, of in enumerate(found) for _ in of]
                numbers, log_p, perturbed, inclusion = zip(*(x for of in found for x in of), strict=True)
                packed = [x.astype("<i4") for x in numbers]
                exact = [_decodes(pieces, x, texts[i]) for i, x in zip(row, packed, strict=True)]
                columns = {
                    "sample": pa.array([s + 1 for of in found for s in range(len(of))], pa.int32()), "n_tokens": pa.array(map(len, packed), pa.int64()),
                    "log_prob": pa.array(log_p, pa.float64()), "perturbed": pa.array(perturbed, pa.float64()), "inclusion": pa.array(inclusion, pa.float64()),
                    "ids": pa.array([x.tobytes() for x in packed], pa.binary()), "round_trip": pa.array(exact, pa.bool_()),
                }
                yield pa.RecordBatch.from_arrays([part.column("doc_id").take(pa.array(row, pa.int64())), *columns.values()], names=["doc_id", *columns])

    return run


def _decodes(pieces: Pieces, ids: np.ndarray, text: str | None) -> bool:
    """Whether piece numbers decode to the text."""
    raw = pieces.raw(ids).tobytes()
    return raw.removeprefix(b" ") == (text or "").encode()


def sample_segmentations(docs: DataFrame, model_file: str, k: int = 3, seed: int = 11, sharpness: float = 1.0) -> DataFrame:
    """Up to k distinct segmentations of every text.

    Returns doc_id, sample (1 is the largest perturbed value), n_tokens, log_prob, perturbed, inclusion, ids (piece
    numbers as little-endian 32-bit) and round_trip (decoding gives the text back).  ``model_file`` is read by the
    driver.
    """
    with open(model_file, "rb") as f:
        model = f.read()
    rows = "doc_id long, sample int, n_tokens long, log_prob double, perturbed double, inclusion double, ids binary, round_trip boolean"
    return plain(docs, "doc_id", "text").mapInArrow(_sample_rows(model, k, seed, sharpness), rows)


def decode(encoded: DataFrame, model_file: str) -> DataFrame:
    """``encoded`` rows with ``ids`` plus the decoded ``text``; null ids decode to null."""
    from pyspark.sql import types as T

    with open(model_file, "rb") as f:
        model = f.read()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = Pieces(model)
        for batch in batches:
            texts = [None if x is None else pieces.decode(np.frombuffer(x, "<i4").tolist()) for x in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, pa.string())], names=[*batch.schema.names, "decoded"])

    return encoded.mapInArrow(run, T.StructType([*encoded.schema.fields, T.StructField("decoded", T.StringType())]))


def tokens(ids):
    """Column of piece numbers (array<int>) from the packed ``ids``; for small results."""
    hexed = F.hex(ids)
    byte = lambda at: F.conv(F.substring(hexed, at, 2), 16, 10).cast("int")
    place = F.sequence(F.lit(0), (F.length(ids) / 4).cast("int") - 1)
    number = lambda i: byte(i * 8 + 1) + byte(i * 8 + 3) * 256 + byte(i * 8 + 5) * 65536 + byte(i * 8 + 7) * 16777216
    return F.when(F.length(ids) == 0, F.array().cast("array<int>")).otherwise(F.transform(place, number))
