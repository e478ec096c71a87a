"""Personal data: fixed patterns, and a semi-Markov conditional random field that adds what they miss.

The patterns (email, ip, card, phone) give base spans, leftmost and non-overlapping per kind.  The field then works
on runs of tokens around digits and at-signs that no base span covers.  A candidate segment is up to MOST_TOKENS
tokens; its score for a kind is the weight of features of the whole span: its shape, digits, separators, checksum,
groups, and the words on both sides.  Dynamic programming over token positions picks boundaries and kinds jointly;
tokens outside segments score 0.  A segment is added if the field's posterior for it reaches ``least``.

Training: exact log-likelihood gradients by forward and backward sums over runs of a bounded sample of documents
(``sample`` rows, the first by a hash of their ids).  Gold segments are base spans, and base spans rewritten into
forms that the patterns don't take (spelled-out at-signs, phones without a plus, spaced dots, dotted cards); the same
runs without rewriting, and runs without base spans, teach what to leave alone.  Without a base span in the sample the
field adds nothing.

Defined cases: null or empty text has no spans; base spans of different kinds may overlap, added spans overlap none;
rows that repeat are judged alike; a run is as long as its text asks for, and is cut only where no segment crosses;
empty tables give empty results; extra columns are ignored (``redact`` keeps them).
"""

from __future__ import annotations

import re
from array import array
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import plain, text_slices

KINDS = ("email", "ip", "card", "phone")
MOST_TOKENS = 16
WINDOW = 64
FEATURES = 1 << 13
FEATURES_EACH = 12
LEAST = 0.9

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+")
# A digit run always matches from its first digit if it matches at all, so later digits need no look.
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_SOME = re.compile(r"[0-9@]")
_MARK = re.compile(r"[0-9]+|@")
_TOKEN = re.compile(r"[0-9]+|[^\W\d_]+|\S")
_AT = re.compile(r"[\[(]at[\])]", re.I)
_SPELLED = re.compile(r" at (?=[A-Za-z0-9-]++\.[A-Za-z0-9-])")

Span = tuple[str, int, int]


def luhn(digits: str) -> bool:
    """The checksum of card numbers."""
    total = sum(map(int, digits[-1::-2])) + sum(d - 9 if d > 9 else d for d in (2 * int(x) for x in digits[-2::-2]))
    return total % 10 == 0


def _emails(text: str) -> Iterator[Span]:
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        found = _DOMAIN.match(text, at + 1) if start < at else None
        if found:
            yield "email", start, found.end()
            done = found.end()
        at = text.find("@", max(at + 1, done))


def base_spans(text: str | None) -> list[Span]:
    """(kind, start, end) in code points by kind in the order of KINDS, then start."""
    if not text or not _SOME.search(text):
        return []
    out = list(_emails(text)) if "@" in text else []
    out += [("ip", *m.span()) for m in _IP.finditer(text) if all(len(x.lstrip("0")) <= 3 and int(x.lstrip("0") or 0) <= 255 for x in m[0].split("."))]
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 13:
            digits = m[0].replace(" ", "").replace("-", "")
            if 13 <= len(digits) <= 19 and luhn(digits):
                out.append(("card", *m.span()))
    if "+" in text:
        out += [("phone", *m.span()) for m in _PHONE.finditer(text) if 9 <= sum(c.isdigit() for c in m[0]) <= 15]
    return out


def told(spans: list[Span]) -> str:
    """kind:start:end, comma-joined, by kind as listed, then start."""
    order = {k: i for i, k in enumerate(KINDS)}
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(spans, key=lambda s: (order[s[0]], s[1], s[2])))


# ---------------------------------------------------------------- runs of tokens


def _marks(text: str) -> list[int]:
    """Starts of the tokens that may be in personal data: numbers, at-signs, and an "at" from a local part to a dotted host."""
    spelled = [m.start() + 1 for m in _SPELLED.finditer(text) if m.start() and text[m.start() - 1] in _LOCAL]
    return sorted(chain(spelled, (m.start() for m in chain(_MARK.finditer(text), _AT.finditer(text)))))


def _free(covered: list[tuple[int, int]], size: int) -> Iterator[tuple[int, int]]:
    """What the covered spans leave of a text of ``size`` characters."""
    at = 0
    for a, b in [*sorted(covered), (size, size)]:
        if a > at:
            yield at, a
        at = max(at, b)


def _before(text: str, low: int, at: int) -> tuple[list[tuple[int, int]], bool]:
    """Up to MOST_TOKENS token spans from ``low`` that end at ``at`` the latest, and whether they are all of these."""
    width = 128
    while True:
        start = max(low, at - width)
        got = [m.span() for m in _TOKEN.finditer(text, start, at)]
        # a start inside a token shortens only the first one
        if start == low or len(got) > MOST_TOKENS:
            return got[-MOST_TOKENS:], start == low and len(got) <= MOST_TOKENS
        width *= 4


def _runs(text: str, covered: list[tuple[int, int]]) -> Iterator[list[tuple[int, int]]]:
    """Token spans around what may be personal data and isn't covered.

    A run has MOST_TOKENS tokens on both sides of each of its marks, or all there are, so every segment with a mark
    lies in one run as a whole, with a token of context on both sides.
    """
    marks, k = _marks(text), 0
    for low, high in _free(covered, len(text)):
        run: list[tuple[int, int]] = []
        while k < len(marks) and marks[k] < low:
            k += 1
        while k < len(marks) and marks[k] < high:
            more, joined = _before(text, run[-1][1] if run else low, marks[k])
            if run and not joined:
                yield run
                run = []
            run += more
            left = 1
            for m in _TOKEN.finditer(text, marks[k], high):
                run.append(m.span())
                left -= 1
                while k < len(marks) and marks[k] < m.end():
                    k, left = k + 1, MOST_TOKENS
                if not left:
                    break
        if run:
            yield run


def _shape(piece: str) -> str:
    out = []
    for c in piece:
        k = "9" if c.isdigit() else "a" if c.isalpha() else " " if c.isspace() else c
        if not out or out[-1] != k:
            out.append(k)
    return "".join(out)[:24]


def _hash(name: str) -> int:
    return xxhash.xxh32_intdigest(name.encode("utf-8", "replace")) % FEATURES


class Candidates:
    """The candidate segments of a run and their features, which the kinds share."""

    def __init__(self, text: str, run: list[tuple[int, int]]):
        where, flat = [], array("H")
        for i, j, features in self._segments(text, run):
            where.append((i, j))
            flat.extend(features)
        self._set(run, where, flat)

    def _set(self, run: list[tuple[int, int]], where: list[tuple[int, int]], flat: array) -> Candidates:
        self.run, self.where = run, where
        self.features = np.array(flat, np.uint16).reshape(len(where), FEATURES_EACH)
        return self

    @classmethod
    def parts(cls, text: str, run: list[tuple[int, int]]) -> Iterator[Candidates]:
        """The run cut where no segment crosses; sums and paths over the parts are those over the run."""
        first = reach = 0
        where, flat = [], array("H")
        for i, j, features in cls._segments(text, run):
            if where and i >= reach:
                yield cls.__new__(cls)._set(run[first:reach], where, flat)
                where, flat = [], array("H")
            if not where:
                first = reach = i
            where.append((i - first, j - first))
            flat.extend(features)
            reach = max(reach, j)
        if where:
            yield cls.__new__(cls)._set(run[first:reach], where, flat)

    @classmethod
    def _segments(cls, text: str, run: list[tuple[int, int]]) -> Iterator[tuple[int, int, list[int]]]:
        """(first token, token after the last, features)."""
        low = [text[a:b].lower() for a, b in run]
        numeric = ["0" <= text[a] <= "9" for a, _ in run]
        for i in range(len(run)):
            if not (numeric[i] or low[i] in "+([" or low[i][0].isalpha()):
                continue
            digits = 0
            for j in range(i, min(len(run), i + MOST_TOKENS)):
                if j > i and run[j][0] - run[j - 1][1] > 1:
                    break
                digits += (run[j][1] - run[j][0]) if numeric[j] else 0
                if not (numeric[j] or low[j][0].isalpha()):
                    continue
                piece = text[run[i][0] : run[j][1]]
                if digits < 4 and "@" not in piece and " at " not in piece and not _AT.search(piece):
                    continue
                yield i, j + 1, cls._features(piece, digits, low[i - 1] if i else "", low[j + 1] if j + 1 < len(low) else "")

    @staticmethod
    def _features(piece: str, digits: int, before: str, after: str) -> list[int]:
        only = "".join(c for c in piece if "0" <= c <= "9")
        groups = re.findall(r"[0-9]+", piece)
        marks = "".join(sorted({c for c in piece if not c.isalnum()}))
        octets = len(groups) == 4 and all(len(g) <= 3 and int(g) <= 255 for g in groups)
        names = (
            "bias", f"shape={_shape(piece)}", f"digits={min(digits, 20)}", f"tokens={min(len(piece), 40) // 4}",
            f"marks={marks[:6]}", f"groups={'-'.join(str(min(len(g), 9)) for g in groups[:6])}",
            f"check={13 <= len(only) <= 19 and luhn(only)}&{any(c.isalpha() for c in piece)}", f"octets={octets}&{marks[:4]}",
            f"at={'@' in piece or ' at ' in piece or bool(_AT.search(piece))}&dot={'.' in piece or 'dot' in piece}",
            f"before={before[:8]}", f"after={after[:8]}", f"edge={piece[:1] if not piece[:1].isalnum() else '_'}&{before[-1:]}&{after[:1]}",
        )
        return [_hash(n) for n in names]


class Field:
    """Weights (kind, feature), and the sums and the best path over the segments of a run."""

    def __init__(self, weights: np.ndarray):
        self.weights = weights

    def scores(self, c: Candidates) -> np.ndarray:
        out = np.zeros((len(c.where), len(KINDS)))
        for i in range(0, len(out), 4096):
            out[i : i + 4096] = self.weights[:, c.features[i : i + 4096]].sum(axis=2).T
        return out

    def marginals(self, c: Candidates, s: np.ndarray) -> np.ndarray:
        """Posterior of each (segment, kind)."""
        n = len(c.run)
        forward, backward = np.full(n + 1, -np.inf), np.full(n + 1, -np.inf)
        forward[0] = backward[n] = 0.0
        joint = np.logaddexp.reduce(s, axis=1)
        ends: dict[int, list[int]] = {}
        starts: dict[int, list[int]] = {}
        for k, (a, b) in enumerate(c.where):
            ends.setdefault(b, []).append(k)
            starts.setdefault(a, []).append(k)
        for t in range(1, n + 1):
            terms = [forward[t - 1]] + [forward[c.where[k][0]] + joint[k] for k in ends.get(t, ())]
            forward[t] = np.logaddexp.reduce(terms)
        for t in range(n - 1, -1, -1):
            terms = [backward[t + 1]] + [backward[c.where[k][1]] + joint[k] for k in starts.get(t, ())]
            backward[t] = np.logaddexp.reduce(terms)
        at = np.array(c.where, np.int64).reshape(-1, 2)
        return np.exp(forward[at[:, 0], None] + s + backward[at[:, 1], None] - forward[n])

    def best(self, c: Candidates, s: np.ndarray) -> list[tuple[int, int]]:
        """(segment, kind) on the path of the highest score."""
        n = len(c.run)
        value, back = [0.0] * (n + 1), [None] * (n + 1)
        kind = s.argmax(1)
        top = s.max(1)
        ends: dict[int, list[int]] = {}
        for k, (_, b) in enumerate(c.where):
            ends.setdefault(b, []).append(k)
        for t in range(1, n + 1):
            value[t] = value[t - 1]
            for k in ends.get(t, ()):
                v = value[c.where[k][0]] + top[k]
                if v > value[t]:
                    value[t], back[t] = v, k
        out, t = [], n
        while t:
            if back[t] is None:
                t -= 1
            else:
                out.append((back[t], int(kind[back[t]])))
                t = c.where[back[t]][0]
        return out

    def spans(self, text: str, base: list[Span], least: float = LEAST) -> list[Span]:
        """Segments on the best path that no base span covers and whose posterior reaches ``least``."""
        out = []
        for run in _runs(text, [(a, b) for _, a, b in base]):
            for c in Candidates.parts(text, run):
                s = self.scores(c)
                if s.max() <= 0:
                    continue
                path = self.best(c, s)
                if path:
                    p = self.marginals(c, s)
                    out += [(KINDS[y], c.run[c.where[k][0]][0], c.run[c.where[k][1] - 1][1]) for k, y in path if p[k, y] >= least]
        return out


# ---------------------------------------------------------------- training


def _rewritten(kind: str, piece: str, turn: int) -> str | None:
    """A form of a base span that the patterns don't take."""
    if kind == "email":
        name, _, host = piece.partition("@")
        return (f"{name} at {host}", f"{name} [at] {host}", f"{name}(at){host}")[turn % 3]
    if kind == "ip":
        return (piece.replace(".", " . "), piece.replace(".", "[.]"))[turn % 2]
    if kind == "card":
        digits = re.sub("[^0-9]", "", piece)
        return ".".join(digits[i : i + 4] for i in range(0, len(digits), 4)) if turn % 2 else "/".join(digits[i : i + 4] for i in range(0, len(digits), 4))
    bare = piece.lstrip("+").split(" ", 1)
    return bare[1] if len(bare) == 2 and sum(c.isdigit() for c in bare[1]) >= 9 else None


def _examples(texts: list[str]) -> Iterator[tuple[Candidates, set[tuple[int, int]]]]:
    """Runs with their gold (segment, kind)."""
    turn = 0
    for text in texts:
        base = base_spans(text)
        for run in _runs(text, [(a, b) for _, a, b in base]):
            for c in Candidates.parts(text, run):
                yield c, set()
        for kind, a, b in base:
            if any(x != (kind, a, b) and x[1] < b and a < x[2] for x in base):
                continue
            before, after = text[max(0, a - 40) : a], text[b : b + 40]
            before = before[before.find(" ") + 1 :] if a > 40 else before
            forms = [text[a:b]] + [x for x in (_rewritten(kind, text[a:b], turn + i) for i in range(2)) if x]
            turn += 1
            for form in forms:
                piece = before + form + after
                run = [m.span() for m in _TOKEN.finditer(piece)][:WINDOW]
                starts, ends = {x: i for i, (x, _) in enumerate(run)}, {y: i + 1 for i, (_, y) in enumerate(run)}
                gold = (starts.get(len(before)), ends.get(len(before) + len(form)))
                c = Candidates(piece, run)
                if gold in c.where:
                    yield c, {(c.where.index(gold), KINDS.index(kind))}


def fit(texts: list[str], rounds: int = 3, rate: float = 0.5, decay: float = 1e-3) -> Field:
    """Maximise the log-likelihood of the gold segments by adaptive gradient steps, in a fixed order."""
    examples = list(_examples(texts))
    weights = np.zeros((len(KINDS), FEATURES))
    field = Field(weights)
    if not any(gold for _, gold in examples):
        weights[:, _hash("bias")] = -50.0
        return field
    weights[:, _hash("bias")] = -2.0
    squares = np.full_like(weights, 1e-2)
    rng = np.random.default_rng(3)
    for _ in range(rounds):
        for i in rng.permutation(len(examples)):
            c, gold = examples[i]
            pull = -field.marginals(c, field.scores(c))
            for k, y in gold:
                pull[k, y] += 1
            some = np.abs(pull).max(1) > 1e-4
            if not some.any():
                continue
            at = c.features[some]
            for y in range(len(KINDS)):
                g = np.zeros(FEATURES)
                np.add.at(g, at, pull[some, y][:, None])
                live = np.flatnonzero(g)
                step = g[live] - decay * weights[y, live]
                squares[y, live] += step * step
                weights[y, live] += rate * step / np.sqrt(squares[y, live])
    return field


def train(docs: DataFrame, sample: int = 500, most: int = 4000) -> Field:
    """Fit on a bounded sample: ``sample`` distinct texts with a digit or at-sign, the first by a hash of their ids.

    Of each only ``most`` characters around its first digit or at-sign are used.  Keys are ranked first, so tasks
    send the driver keys, and then no more than the sample's excerpts.
    """
    some = plain(docs, "doc_id", "text").where(F.col("text").rlike("[0-9@]")).withColumns({"h": F.xxhash64("doc_id"), "t": F.xxhash64("text")})
    keys = some.select("h", "t").distinct().orderBy("h", "t").limit(sample)
    first = F.greatest(F.regexp_instr("text", F.lit("[0-9@]")) - 200, F.lit(1))
    chosen = some.join(F.broadcast(keys), ["h", "t"]).select("h", "t", F.substring(F.col("text"), first, F.lit(most)).alias("text"))
    return fit([r.text for r in chosen.dropDuplicates(["h", "t"]).orderBy("h", "t").collect()])


def _find_rows(shared, least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        field: Field = shared.value
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32()), ("base", pa.bool_())]))
        for batch in batches:
            for part in text_slices(batch):
                rows = []
                for text in part.column("text").to_pylist():
                    base = base_spans(text)
                    more = field.spans(text, base, least) if text else []
                    rows.append([{"kind": k, "start": a, "end": b, "base": i < len(base)} for i, (k, a, b) in enumerate(base + more)])
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(rows, kind)], names=[*part.schema.names, "spans"])

    return run


def find(docs: DataFrame, field: Field | None = None, least: float = LEAST) -> DataFrame:
    """``docs`` plus spans: array of (kind, start, end, base), base spans first in the order of the kinds."""
    field = field or train(docs)
    shared = docs.sparkSession.sparkContext.broadcast(field)
    span = T.ArrayType(T.StructType([T.StructField("kind", T.StringType()), T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType()), T.StructField("base", T.BooleanType())]))
    return docs.mapInArrow(_find_rows(shared, least), T.StructType([*docs.schema.fields, T.StructField("spans", span)]))


def summary(found: DataFrame) -> DataFrame:
    """Counts of base spans by kind, the hash of their list, and the list of all spans."""
    span = lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))
    rank = lambda s: F.array_position(F.array(*[F.lit(k) for k in KINDS]), s["kind"])
    base = F.filter("spans", lambda s: s["base"])
    every = F.transform(F.array_sort(F.transform("spans", lambda s: F.struct(rank(s).alias("r"), s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind")))), span)

    def count(kind: str):
        return F.size(F.filter("spans", lambda s: s["base"] & (s["kind"] == kind))).cast("long").alias(f"n_{kind}")

    counts = [count(k) for k in KINDS]
    return found.select("doc_id", *counts, F.sha2(F.concat_ws(",", F.transform(base, span)).cast("binary"), 256).alias("base_sha256"), F.concat_ws(",", every).alias("spans"))


def redact(docs: DataFrame, field: Field | None = None, least: float = LEAST) -> DataFrame:
    """``docs`` with every span of personal data in ``text`` replaced by its kind in brackets; all columns stay."""
    field = field or train(docs)
    shared = docs.sparkSession.sparkContext.broadcast(field)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in text_slices(batch):
                texts = []
                for text in part.column("text").to_pylist():
                    base = base_spans(text)
                    spans = sorted(((a, b, k) for k, a, b in base + (shared.value.spans(text, base, least) if text else [])))
                    if spans:
                        out, at = [], 0
                        for a, b, k in spans:
                            if a >= at:
                                out += [text[at:a], f"[{k.upper()}]"]
                            at = max(at, b)
                        text = "".join(out) + text[at:]
                    texts.append(text)
                yield part.set_column(part.schema.get_field_index("text"), "text", pa.array(texts, pa.string()))

    return docs.mapInArrow(run, docs.schema)
