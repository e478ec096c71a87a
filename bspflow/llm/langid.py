"""Language identification: multinomial naive Bayes over hashed character n-grams.

Training counts the hashed n-grams of all labelled texts, one dense table a language of ``buckets`` counts: a
task adds up its own texts and sends only non-zero counts, so what moves is bounded by tasks x languages x
buckets and the model by languages x buckets.  The log-probability matrix is broadcast; a batch is scored in
numpy by adding matrix rows of the n-grams that occur.

Defined cases: null text, or text without a letter (Unicode's L categories), is ``und`` with score 0; without any
labelled text every document is ``und``; ties go to the first language in code point order; a very long text is hashed
in segments and scored as a whole; repeated rows count as often as they occur and get equal predictions; empty tables
give empty results; extra columns are ignored.  More than ``LANGUAGES_MOST`` labels raise before any count is gathered.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import plain, text_slices

GRAMS = (1, 2, 3)
BUCKETS = 1 << 15
LANGUAGES_MOST = 512
UNKNOWN = "und"


def _segments(texts: list[str], most: int) -> Iterator[tuple[int, np.ndarray, int]]:
    """(text, code points, starts): texts in segments of at most ``most`` n-gram starts, with the code points these need.

    A text gets one space before and after; white space and digits fold.
    """
    more = max(GRAMS) - 1
    for i, text in enumerate(texts):
        low = f" {text.lower()} "
        for at in range(0, len(low), most):
            c = np.frombuffer(low[at : at + most + more].encode("utf-32-le", "surrogatepass"), np.uint32)
            yield i, np.where((c >= 48) & (c <= 57), np.uint32(48), np.where(c <= 32, np.uint32(32), c)), min(most, len(c))


def gram_buckets(texts: list[str], grams: tuple[int, ...] = GRAMS, buckets: int = BUCKETS, most: int = 1 << 16) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Buckets of all n-grams of all texts, in turns of one n and about ``most`` characters.

    A turn is (texts, counts, buckets): which texts it has n-grams of, how many of each, and those of one after another.
    Long texts take several turns, so work arrays stay small whatever a text's length is.
    """
    if max(grams) > max(GRAMS):
        raise ValueError(f"n-grams have {max(GRAMS)} characters at most")
    held, size = [], 0
    for segment in _segments(texts, most):
        held.append(segment)
        size += len(segment[1])
        if size >= most:
            yield from _turns(held, grams, buckets)
            held, size = [], 0
    if held:
        yield from _turns(held, grams, buckets)


def _turns(held: list[tuple[int, np.ndarray, int]], grams: tuple[int, ...], buckets: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    who, codes, starts = zip(*held, strict=True)
    c = np.concatenate(codes)
    lengths, starts = np.array([len(x) for x in codes], np.int32), np.array(starts, np.int32)
    first = np.cumsum(lengths) - lengths
    h = np.zeros(len(c), np.uint32)
    for n in range(1, max(grams) + 1):
        h = (h[: len(c) - n + 1] if n > 1 else h) * np.uint32(0x01000193) ^ c[n - 1 :]
        if n in grams:
            # a segment's n-grams begin at its starts and end within it
            many = np.maximum(np.minimum(starts, lengths - n + 1), 0)
            step = np.zeros(len(c) + 1, np.int8)
            np.add.at(step, first[many > 0], 1)
            np.add.at(step, (first + many)[many > 0], -1)
            mixed = h[np.cumsum(step[: len(h)], dtype=np.int8).astype(bool)]
            mixed = (mixed ^ np.uint32(n * 0x9E3779B1 & 0xFFFFFFFF)) * np.uint32(0x85EBCA6B)
            mixed = (mixed ^ (mixed >> np.uint32(15))) * np.uint32(0xC2B2AE35)
            yield np.array(who)[many > 0], many[many > 0], (mixed >> np.uint32(32 - buckets.bit_length() + 1)).astype(np.int32)


def has_letter(text: str | None) -> bool:
    """Whether any character is a letter (general categories L*)."""
    return bool(text) and any(map(str.isalpha, text))


def _train_rows(grams: tuple[int, ...], buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables: dict[str, np.ndarray] = {}
        docs: dict[str, int] = {}
        for batch in batches:
            for part in text_slices(batch, budget=1 << 18):
                by: dict[str, list[str]] = {}
                for lang, text in zip(part.column("lang").to_pylist(), part.column("text").to_pylist(), strict=True):
                    if has_letter(text):
                        by.setdefault(lang, []).append(text)
                for lang, texts in by.items():
                    table = tables.setdefault(lang, np.zeros(buckets, np.int64))
                    for _, _, b in gram_buckets(texts, grams, buckets):
                        table += np.bincount(b, minlength=buckets)
                    docs[lang] = docs.get(lang, 0) + len(texts)
                if len(tables) > 64:  # many labels: send on what there is rather than hold it
                    yield from _table_rows(tables, docs)
                    tables, docs = {}, {}
        yield from _table_rows(tables, docs)

    return run


def _table_rows(tables: dict[str, np.ndarray], docs: dict[str, int]) -> Iterator[pa.RecordBatch]:
    for lang, table in tables.items():
        at = np.flatnonzero(table)
        b = np.concatenate(([-1], at)).astype(np.int32)
        n = np.concatenate(([docs[lang]], table[at]))
        yield pa.RecordBatch.from_arrays([pa.array([lang] * len(b), pa.string()), pa.array(b), pa.array(n)], names=["lang", "bucket", "n"])


class Model:
    """Languages, their log priors, and a matrix (languages, buckets) of log probabilities."""

    def __init__(self, languages: list[str], prior: np.ndarray, weights: np.ndarray, grams: tuple[int, ...]):
        self.languages, self.prior, self.weights, self.grams = languages, prior, weights, grams

    def scores(self, texts: list[str]) -> np.ndarray:
        """Log-likelihoods (texts, languages), the prior included."""
        out = np.zeros((len(texts), len(self.languages)))
        for who, many, b in gram_buckets(texts, self.grams, self.weights.shape[1]):
            starts = np.cumsum(many) - many
            for k, weights in enumerate(self.weights):
                np.add.at(out[:, k], who, np.add.reduceat(weights[b], starts, dtype=np.float64))
        return out + self.prior


def train(docs: DataFrame, grams: tuple[int, ...] = GRAMS, buckets: int = BUCKETS, smoothing: float = 0.5) -> Model:
    """Fit on ``docs``(text, lang); rows with null text, null label or no letter are left out."""
    known = docs.where("lang IS NOT NULL AND text IS NOT NULL")
    rows = known.select("lang", "text").mapInArrow(_train_rows(grams, buckets), "lang string, bucket int, n long")
    if (labels := known.select("lang").distinct().limit(LANGUAGES_MOST + 1).count()) > LANGUAGES_MOST:
        raise ValueError(f"{labels} labels or more; a model has {LANGUAGES_MOST} at most")
    total = rows.groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toPandas()
    languages = sorted(total["lang"].unique(), key=lambda s: s.encode())
    index = {x: k for k, x in enumerate(languages)}
    counts = np.full((len(languages), buckets), smoothing)
    prior = np.zeros(len(languages))
    k = total["lang"].map(index).to_numpy(np.int64) if len(total) else np.zeros(0, np.int64)
    b, n = total["bucket"].to_numpy(np.int64), total["n"].to_numpy(np.float64)
    counts[k[b >= 0], b[b >= 0]] += n[b >= 0]
    prior[k[b < 0]] = n[b < 0]
    weights = np.log(counts / counts.sum(1, keepdims=True)) if languages else counts
    return Model(languages, np.log(prior / prior.sum()) if languages else prior, weights.astype(np.float32), grams)


def _predict_rows(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model: Model = shared.value
        for batch in batches:
            for part in text_slices(batch, budget=1 << 18):
                texts = part.column("text").to_pylist()
                known = [i for i, t in enumerate(texts) if has_letter(t)] if model.languages else []
                lang, score = [UNKNOWN] * len(texts), np.zeros(len(texts))
                if known:
                    s = model.scores([texts[i] for i in known])
                    best = s.argmax(1)
                    p = 1 / np.exp(s - s.max(1, keepdims=True)).sum(1)
                    for i, k, x in zip(known, best, p, strict=True):
                        lang[i], score[i] = model.languages[k], min(1.0, float(x))
                arrays = [part.column(n) for n in part.schema.names] + [pa.array(lang, pa.string()), pa.array(score)]
                yield pa.RecordBatch.from_arrays(arrays, names=[*part.schema.names, "lang_pred", "score"])

    return run


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """``docs`` (with a text column) plus lang_pred and score, the posterior probability of the prediction."""
    from pyspark.sql import types as T

    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = T.StructType([*docs.schema.fields, T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
    return docs.mapInArrow(_predict_rows(shared), schema)


def held_out(key: Column) -> Column:
    """One id in five, by its text's CRC-32; a null id is not held out."""
    return F.coalesce(F.crc32(key.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def identify(docs: DataFrame, grams: tuple[int, ...] = GRAMS, buckets: int = BUCKETS) -> DataFrame:
    """Train on the documents that are not held out, predict all: doc_id, held_out, lang_pred, score."""
    model = train(plain(docs, "doc_id", "text", "lang").where(~held_out(F.col("doc_id"))), grams, buckets)
    told = predict(plain(docs, "doc_id", "text"), model)
    return told.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
