"""The operators of the llm subpackage against plain Python, on small tables with nulls, blanks, ties and repeats."""

import hashlib
import math
import random
import re

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from bspflow.llm import ann, bitslice, langid, pii, queries, rollup, simhash, spiece, tokens_out
from bspflow.llm.common import shared_path
from bspflow.llm.mixing import mix_sources, source_targets
from bspflow.llm.substring import substring_dedup

DOCS = "doc_id long, text string, lang string, source string, n_chars long, fp long, size long"


def docs(spark, texts, sources=None, langs=None):
    rows = [(i, t, (langs or ["en"] * len(texts))[i], (sources or ["a"] * len(texts))[i], len(t or ""), 1, 2) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS)


def words(t):
    return (t or "").encode().split()


# ---------------------------------------------------------------- 1


def plain_dedup(texts, w):
    first = {}
    for i, t in enumerate(texts):
        ws = words(t)
        for p in range(len(ws) - w + 1):
            first.setdefault(tuple(ws[p : p + w]), i)
    out = {}
    for i, t in enumerate(texts):
        ws = words(t)
        gone = [False] * len(ws)
        for p in range(len(ws) - w + 1):
            if first[tuple(ws[p : p + w])] < i:
                gone[p : p + w] = [True] * w
        out[i] = (len(ws), sum(gone), b" ".join(x for x, g in zip(ws, gone, strict=True) if not g).decode())
    return out


def test_substring_dedup(spark):
    r = random.Random(1)
    shared = " ".join(r.choice("abcdefgh") for _ in range(30))
    texts = [None, "", " \t\n", "x " * 9, shared, f"new {shared} words", shared, "a\x0bb\x0cc  d", f"{shared}\n{shared}", "q w e r t y " * 200]
    got = {x.doc_id: (x.n_words, x.n_removed, x.kept_text) for x in substring_dedup(docs(spark, texts), window=5, filter_bits=1 << 20).collect()}
    assert got == plain_dedup(texts, 5)
    assert substring_dedup(docs(spark, texts).limit(0), window=5).count() == 0


def test_substring_dedup_same_id_and_null_id(spark):
    t = "a b c d e f"
    df = spark.createDataFrame([(5, t), (5, t), (None, t), (7, t)], "doc_id long, text string")
    got = sorted((x.doc_id or -1, x.n_removed) for x in substring_dedup(df, window=3, filter_bits=1 << 20).collect())
    assert got == [(-1, 0), (5, 0), (5, 0), (7, 6)]


# ---------------------------------------------------------------- 2


def test_mixing_meets_its_targets(spark):
    r = random.Random(2)
    texts = [" ".join(["w"] * r.randint(0, 30)) for _ in range(300)] + [None, ""]
    sources = [r.choice(["b", "a", "c", None, "é"]) for _ in texts]
    got = mix_sources(docs(spark, texts, sources), range_rows=16).collect()
    assert len(got) == len(texts) and all(x.taken <= 3 * x.size and x.size == len(words(texts[x.doc_id])) for x in got)
    by = {}
    for x in got:
        by.setdefault(x.source, []).append(x)
    for rows in by.values():
        assert abs(sum(x.taken for x in rows) - rows[0].target) < 1 and rows[0].source_size == sum(x.size for x in rows)
    assert abs(sum(rows[0].target for rows in by.values()) - sum(x.size for x in got)) < 1e-6
    again = mix_sources(docs(spark, texts, sources).repartition(7), range_rows=16).collect()
    assert sorted((x.doc_id, x.taken) for x in again) == sorted((x.doc_id, x.taken) for x in got)


def plain_targets(sizes):
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(sorted(sizes, key=lambda s: (s is None, (s or "").encode())))}
    target, open_, total = {}, set(sizes), sum(sizes.values())
    while True:
        left = total - sum(target.values())
        all_weight = sum(weight[s] for s in open_)
        over = [s for s in open_ if left * weight[s] / all_weight > 3 * sizes[s] + 1e-9]
        if not over:
            return target | {s: left * weight[s] / all_weight for s in open_}
        for s in over:
            target[s] = 3 * sizes[s]
            open_.remove(s)


def test_targets_reshare_the_excess(spark):
    for sizes in ({"a": 1, "b": 50, "c": 1000}, {"a": 0, "b": 10, None: 5}, {"a": 3, "b": 4, "c": 5, "d": 600, "e": 1}):
        rows = spark.createDataFrame([(s, n) for s, n in sizes.items()], "source string, size long")
        got = {x.source: x.target for x in source_targets(rows).collect()}
        want = plain_targets(sizes)
        assert all(abs(got[s] - want[s]) < 1e-6 for s in sizes), (sizes, got, want)
    assert mix_sources(docs(spark, ["x"]).limit(0)).count() == 0


# ---------------------------------------------------------------- 3 and 9


@pytest.fixture(scope="module")
def vectors(spark):
    r = np.random.default_rng(3)
    rows = [(i, [float(x) for x in r.normal(size=8) / 3]) for i in range(400)]
    rows += [(400, None), (401, [0.0] * 8), (402, [float("nan")] + [0.1] * 7), (403, [None] + [0.1] * 7), (404, rows[20][1]), (405, rows[20][1]), (406, [1.0, 2.0])]
    return spark.createDataFrame(rows, "vec_id long, embedding array<float>"), {i: np.array(v, np.float32).astype(np.float64) for i, v in rows if v and len(v) == 8 and None not in v and not np.isnan(v).any()}


def test_nearest_recall_scores_and_ties(spark, vectors):
    df, plain = vectors
    plain = {i: v for i, v in plain.items() if v.any()}
    got = {}
    for x in ann.nearest(df, df.where("vec_id % 20 = 0"), k=10, leaf_rows=32).collect():
        got.setdefault(x.query_id, []).append((x.rank, x.vec_id, x.score))
    hit = 0
    assert set(got) == {i for i in plain if i % 20 == 0}
    for q, rows in got.items():
        rows.sort()
        want = sorted(((-float((plain[q] * v).sum()), i) for i, v in plain.items() if i != q))[:10]
        assert [r for r, *_ in rows] == list(range(1, 11)) and all(abs(s - (plain[q] * plain[i]).sum()) < 1e-12 for _, i, s in rows)
        assert [(-s, i) for _, i, s in rows] == sorted((-s, i) for _, i, s in rows)
        hit += len({i for _, i, _ in rows} & {i for _, i in want})
    assert hit >= 0.9 * 10 * len(got)


def test_nearest_with_few_candidates(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (20, [0.5, 0.5]), (21, [1.0, 1.0])], "vec_id long, embedding array<float>")
    got = [(x.query_id, x.rank, x.vec_id) for x in ann.nearest(df, df.where("vec_id % 20 = 0")).orderBy("query_id", "rank").collect()]
    assert got == [(0, 1, 21), (0, 2, 20), (20, 1, 21), (20, 2, 0)]
    assert ann.nearest(df.limit(0), df.limit(0)).count() == 0


def test_recall_on_the_given_vectors(spark, sf):
    df = spark.read.parquet(f"{sf}/embeddings.parquet")
    asked = df.where("vec_id % 20 = 0")
    found = {(x.query_id, x.vec_id) for x in ann.nearest(df, asked).collect()}
    true = {(x.query_id, x.vec_id) for x in ann.exact_nearest(df, asked).collect()}
    assert len(found & true) >= 0.9 * len(true)


def test_bit_sliced_top_k(spark, vectors):
    df, plain = vectors
    z = {i: np.floor(64 * v).astype(np.int64) for i, v in plain.items()}
    got = {}
    for x in bitslice.exact_top_k(df, df.where("vec_id % 20 = 0"), k=10, block=100, query_block=7).collect():
        got.setdefault(x.query_id, []).append((x.rank, x.vec_id, x.score))
    for q in (i for i in z if i % 20 == 0):
        want = sorted((-int(z[q] @ v), i) for i, v in z.items() if i != q)[:10]
        assert [(-s, i) for _, i, s in sorted(got[q])] == want


def test_signed_digits():
    for q in (*range(-300, 300), 1 << 24, -(1 << 24)):
        assert sum(d << p for p, d in bitslice.signed_digits(q)) == q


# ---------------------------------------------------------------- 4


def plain_fp(t):
    ws = (t or "").encode().lower().split()
    if not ws:
        return 0
    shingles = [b" ".join(ws[i : i + 4]) for i in range(len(ws) - 3)] or [b" ".join(ws)]
    hs = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def test_simhash_components(spark):
    r = random.Random(4)
    base = [" ".join("".join(r.choice("abcde") for _ in range(3)) for _ in range(120)) for _ in range(12)]
    texts = [None, "", "Word", "word"]
    for t in base:
        ws = t.split()
        for n in range(5):
            ws = ws[:]
            ws[r.randrange(len(ws))] = f"x{n}"
            texts.append(" ".join(ws).upper() if n % 2 else " ".join(ws))
    prints = [plain_fp(t) for t in texts]
    label = list(range(len(texts)))
    for _ in texts:
        for i, a in enumerate(prints):
            for j, b in enumerate(prints):
                if (a ^ b).bit_count() <= 4:
                    label[i] = label[j] = min(label[i], label[j])
    for most in (4096, 1):
        got = {x.doc_id: (x.fp & (1 << 64) - 1, x.component_id) for x in simhash.near_duplicate_components(docs(spark, texts), most=most).collect()}
        assert got == {i: (prints[i], label[i]) for i in range(len(texts))}, most
    assert simhash.near_duplicate_components(docs(spark, texts).limit(0)).count() == 0


# ---------------------------------------------------------------- 5


@pytest.fixture(scope="module")
def pieces():
    with open(queries.piece_model(), "rb") as f:
        return spiece.Pieces(f.read())


def test_round_trip_of_any_text(spark, pieces):
    texts = [None, "", " ", "a", "two  spaces ", "\n\ttabs", "漢字 ▁ é🎉\x00", "x" * 3000, "the cat sat on the mat " * 300]
    got = spiece.sample_segmentations(docs(spark, texts), queries.piece_model(), k=3).collect()
    assert all(x.round_trip for x in got) and {x.doc_id for x in got} == set(range(len(texts)))
    for i in range(len(texts)):
        mine = sorted((x for x in got if x.doc_id == i), key=lambda x: x.sample)
        assert len({bytes(x.ids) for x in mine}) == len(mine) and [x.perturbed for x in mine] == sorted((x.perturbed for x in mine), reverse=True)
    again = spiece.sample_segmentations(docs(spark, texts).repartition(3), queries.piece_model(), k=3).collect()
    assert sorted((x.doc_id, x.sample, bytes(x.ids)) for x in got) == sorted((x.doc_id, x.sample, bytes(x.ids)) for x in again)
    back = spiece.decode(spiece.sample_segmentations(docs(spark, texts), queries.piece_model(), k=1).select("doc_id", "ids"), queries.piece_model())
    assert {x.doc_id: x.decoded for x in back.collect()} == {i: t or "" for i, t in enumerate(texts)}


def test_samples_follow_the_lattice(pieces):
    number = {pieces.text[i].decode(): i for i in range(259, len(pieces.text))}

    def segmentations(u, acc=(), w=0.0):
        if not u:
            yield acc, w
        for n in range(1, len(u) + 1):
            if u[:n] in number:
                yield from segmentations(u[n:], (*acc, number[u[:n]]), w + pieces.weights[number[u[:n]]])

    every = [(a + b, x + y) for a, x in segmentations(" the") for b, y in segmentations(" cat")]
    z = np.logaddexp.reduce([w for _, w in every])
    p = {s: math.exp(w - z) for s, w in every}
    n, first, second = 3000, {}, {}
    for start in range(0, n, 500):
        for rows in spiece.sample_batch(pieces, list(range(start, start + 500)), ["the cat"] * 500, 2, 1):
            a, b = (tuple(x[0].tolist()) for x in rows)
            assert a != b and abs(rows[0][1] - math.log(p[a])) < 1e-9
            first[a], second[b] = first.get(a, 0) + 1, second.get(b, 0) + 1
    for s in sorted(p, key=p.get)[-4:]:
        assert abs(first.get(s, 0) / n - p[s]) < 0.04
        assert abs(second.get(s, 0) / n - sum(p[a] * p[s] / (1 - p[a]) for a in p if a != s)) < 0.04


# ---------------------------------------------------------------- 6


def test_permutation_is_a_bijection():
    for n in (1, 2, 3, 5, 16, 17, 1000):
        order = tokens_out.Permutation(n, 9)
        slots = order.slot(np.arange(n))
        assert sorted(slots.tolist()) == list(range(n)) and (order.index(slots) == np.arange(n)).all()


def test_training_order_holds_every_token(spark):
    texts = ["abc", "", None, "é" * 50, "x" * 1000, "abc", "0123456789"]
    path = shared_path(spark, "t")
    m = tokens_out.write_training_order(docs(spark, texts), path, tokens_out.byte_tokens(F.col("text")), length=16, shard_rows=8)
    rows = tokens_out.read_slots(spark, path).orderBy("slot").collect()
    assert [x.slot for x in rows] == list(range(m["sequences"])) and all(len(x.tokens) == 16 and x.shard == x.slot // 8 for x in rows)
    order = tokens_out.Permutation(m["sequences"], m["key"])
    assert all(order.slot(np.array([x.seq]))[0] == x.slot for x in rows)
    stream = b"".join(bytes(x.tokens) for x in sorted(rows, key=lambda x: x.seq))
    assert stream[m["tokens"] :].strip(b"\xff") == b""
    assert sorted(stream[: m["tokens"]].split(b"\xff")[:-1]) == sorted(t.encode() for t in texts if t is not None)
    assert [x.slot for x in tokens_out.read_slots(spark, path, 5, 4).orderBy("slot").collect()] == [5, 6, 7, 8]


# ---------------------------------------------------------------- 7


def plain_pii(t):
    out = [("email", *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = re.sub("[^0-9]", "", m[0])
        if 13 <= len(d) <= 19 and pii.luhn(d):
            out.append(("card", *m.span()))
    return out + [("phone", *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= len(re.sub("[^0-9]", "", m[0])) <= 15]


def test_base_spans_equal_the_patterns():
    r = random.Random(5)
    fixed = ["", "a@b.c d@e.f.g", "@x.y", "a@b a@b.c@d.e", "1.2.3.4.5.6.7.8", "001.002.3.255 256.1.1.1", "4111 1111 1111 1111", "+1 (743) 555-3824", "++1 2 3 4 5 6 7 8 9", "é1@ü.de", "²³ 4111-1111-1111-1111"]
    for t in fixed + ["".join(r.choice("ab1.@+- 0(9é") for _ in range(60)) for _ in range(3000)]:
        assert pii.base_spans(t) == plain_pii(t), t


def test_long_runs_stay_linear():
    for t in ("1" * 200_000, "a" * 200_000, "1." * 100_000, "a@" * 50_000, "+1 " * 60_000):
        pii.base_spans(t)


def test_field_adds_forms_that_the_patterns_miss_and_keeps_base_spans():
    r = random.Random(6)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(r.randint(2, 6)))
    texts = [f"{word()} {word()} +1 ({r.randint(200, 999)}) 555-{r.randint(1000, 9999)} {word()} {word()} {word()} {r.randint(1, 9999)} {word()} {word()}" for _ in range(200)]
    field = pii.fit(texts)
    t = "please call (743) 555-3824 now"
    assert ("phone", 12, 26) in field.spans(t, pii.base_spans(t))
    assert field.spans("born in 1984 with 12345 things", []) == []
    assert pii.fit(["no data here 12"]).spans(t, []) == []


def phone_field(r):
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(r.randint(2, 6)))
    return pii.fit([f"{word()} {word()} +1 ({r.randint(200, 999)}) 555-{r.randint(1000, 9999)} {word()} {word()} {word()} {r.randint(1, 9999)} {word()} {word()}" for _ in range(200)])


def test_an_entity_is_found_at_every_offset_from_an_earlier_digit():
    field = phone_field(random.Random(6))
    for n in range(130):
        for fill in ("x " * 80, "ab cde " * 30):
            t = "room 7 " + fill[:n].rstrip() + " (743) 555-3824 now"
            assert field.spans(t, pii.base_spans(t)) == [("phone", len(t) - 18, len(t) - 4)], t


def test_spelled_out_addresses_are_found_without_a_digit_or_at_sign():
    r = random.Random(9)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(r.randint(2, 6)))
    field = pii.fit([f"{word()} {word()} {word()}.{word()}@{word()}.org {word()} {word()} look at {word()} {word()}" for _ in range(300)])
    for form in ("anna.b at example.org", "anna.b [at] example.org", "anna.b(at)example.org"):
        for fill in ("", "word " * 50):
            t = f"{fill}write to {form} please {fill}"
            at = t.index(form)
            assert field.spans(t, pii.base_spans(t)) == [("email", at, at + len(form))], (form, field.spans(t, []))
    assert field.spans("look at this. we met at noon. sit at home", []) == []


def test_every_segment_with_a_mark_lies_in_one_part_of_a_run():
    r = random.Random(8)
    for _ in range(200):
        t = "".join(r.choice(["a", "bc ", " ", "1", "23", "@", "(at)", ". ", "  ", "word " * r.randint(1, 25)]) for _ in range(r.randint(1, 60)))
        covered, marks, want, got = [(a, b) for _, a, b in pii.base_spans(t)], pii._marks(t), [], []
        for low, high in pii._free(covered, len(t)):
            whole = [m.span() for m in pii._TOKEN.finditer(t, low, high)]
            want += [(whole[i][0], whole[j - 1][1], f) for i, j, f in pii.Candidates._segments(t, whole)]
        for run in pii._runs(t, covered):
            got += [(c.run[i][0], c.run[j - 1][1], f) for c in pii.Candidates.parts(t, run) for (i, j), f in zip(c.where, c.features.tolist(), strict=True)]
        assert sorted(want) == sorted(got) and all(any(a <= m < b for m in marks) for a, b, _ in got)


def test_best_path_is_the_best_of_all_segmentations():
    field = pii.Field(np.random.default_rng(7).normal(size=(len(pii.KINDS), pii.FEATURES)))
    t = "a 12345 b@c 99 8888"
    run = [m.span() for m in pii._TOKEN.finditer(t)][:8]
    c = pii.Candidates(t, run)
    s = field.scores(c)

    def every(at):
        if at == len(run):
            yield 0.0
            return
        yield from every(at + 1)
        for k, (a, b) in enumerate(c.where):
            if a == at:
                for y in range(len(pii.KINDS)):
                    yield from (s[k, y] + rest for rest in every(b))

    totals = np.array(list(every(0)))
    assert abs(sum(s[k, y] for k, y in field.best(c, s)) - totals.max()) < 1e-9
    assert (field.marginals(c, s).sum(1) <= 1 + 1e-9).all()


def test_pii_query_columns_and_redaction(spark):
    df = docs(spark, [None, "", "mail a@b.co or 1.2.3.4", "none"])
    rows = {x.doc_id: x for x in pii.summary(pii.find(df)).collect()}
    assert (rows[2].n_email, rows[2].n_ip, rows[2].n_card, rows[2].n_phone) == (1, 1, 0, 0)
    assert rows[2].base_sha256 == hashlib.sha256(b"email:5:11,ip:15:22").hexdigest() and rows[2].spans == "email:5:11,ip:15:22"
    assert rows[0].spans == "" and rows[0].base_sha256 == hashlib.sha256(b"").hexdigest()
    assert {x.doc_id: x.text for x in pii.redact(df).collect()} == {0: None, 1: "", 2: "mail [EMAIL] or [IP]", 3: "none"}


def test_pipeline_keeps_texts_when_no_language_is_labelled(spark):
    import corpus_pipeline

    df = docs(spark, ["some words", "12 34", None, "", "ein Satz"], langs=[None] * 5)
    assert sorted(x.doc_id for x in corpus_pipeline.identify_language(spark, df, "").collect()) == [0, 4]


# ---------------------------------------------------------------- 8


def test_ledger_is_idempotent_and_survives_compaction(spark):
    kind = "doc_id long, source string, lang string, tokenizer string, tokens long"
    one = spark.createDataFrame([(1, "a", "en", "w", 5), (2, "a", "en", "w", 7), (3, None, "fr", "w", None)], kind)
    two = spark.createDataFrame([(1, "a", "en", "w", 6), (2, "a", "en", "w", 7)], kind)
    ledger = rollup.Ledger(spark, shared_path(spark, "ledger"))
    assert ledger.commit("b1", rollup.signed_changes(None, one)) and not ledger.commit("b1", rollup.signed_changes(None, one))
    read = lambda: {(x.source, x.lang): (x.docs, x.tokens) for x in ledger.totals().collect()}
    assert read() == {("a", "en"): (2, 12), (None, "fr"): (1, 0)}
    ledger.compact()
    assert not ledger.commit("b1", rollup.signed_changes(None, one)) and read()[("a", "en")] == (2, 12)
    assert ledger.commit("b2", rollup.signed_changes(one, two))
    ledger.compact()
    assert read() == {("a", "en"): (2, 13)} and ledger.committed() == {"b1", "b2"}


# ---------------------------------------------------------------- 10


def test_language_of_unseen_texts(spark):
    r = random.Random(8)
    make = {"en": ["the", "and", "tion", "ing", "of"], "de": ["der", "und", "sch", "keit", "ß"], "fr": ["les", "et", "é", "oux", "que"]}
    rows = [(lang, " ".join(r.choice(make[lang]) + r.choice(["a", "e", ""]) for _ in range(30))) for lang in make for _ in range(60)]
    r.shuffle(rows)
    df = docs(spark, [t for _, t in rows] + [None, "123 !!", ""], langs=[x for x, _ in rows] + [None, "en", "en"])
    got = {x.doc_id: x for x in langid.identify(df).collect()}
    held = [i for i in range(len(rows)) if got[i].held_out]
    import zlib

    assert held == [i for i in range(len(rows)) if zlib.crc32(str(i).encode()) % 5 == 0]
    assert sum(got[i].lang_pred == rows[i][0] for i in held) >= 0.95 * len(held)
    assert [got[i].lang_pred for i in range(len(rows), len(rows) + 3)] == ["und"] * 3
    assert all(0 <= x.score <= 1 for x in got.values())
    assert langid.identify(df.limit(0)).count() == 0


def test_accuracy_on_the_given_documents(spark, sf):
    df = spark.read.parquet(f"{sf}/documents.parquet")
    got = langid.identify(df).join(df.select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert (got.lang == got.lang_pred).mean() >= 0.95


def test_carried_columns_stay_with_their_rows(spark):
    """Rows sharing an id, or having none, are taken each for itself and keep their own text."""
    rows = [(1, "a b c", "s"), (1, "d e f", "s"), (None, "g h", "s"), (None, "i", None), (2, None, "t"), (3, "j k l m", "t")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mix_sources(df, carry=("text",)).collect()
    key = lambda x: (str(x[0]), str(x[1]), str(x[2]))
    assert sorted(((x.doc_id, x.text, x.source) for x in got), key=key) == sorted(rows, key=key)
    assert all(x["size"] == len((x.text or "").split()) for x in got)
    plainly = sorted((str(x.doc_id), x["size"], x.taken) for x in mix_sources(df).collect())
    assert sorted((str(x.doc_id), x["size"], x.taken) for x in got) == plainly
    with pytest.raises(ValueError):
        mix_sources(df, carry=("size",))


# ---------------------------------------------------------------- the pipeline


def test_pipeline_stages_take_effect(spark, sf):
    import corpus_pipeline as p

    df = spark.read.parquet(f"{sf}/documents.parquet")
    names = [n for n, _ in p.STAGES]
    assert len(names) == 5
    kept = p.identify_language(spark, df, sf)
    assert kept.columns == list(p.COLUMNS) and kept.count() == df.where(F.col("text").rlike(r"\p{L}")).count()
    fewer = p.drop_near_copies(spark, df, sf)
    label = {x.doc_id: x.component_id for x in simhash.near_duplicate_components(df).collect()}
    assert {x.doc_id for x in fewer.collect()} == set(label.values())
    clean = {x.doc_id: x.text for x in p.redact_personal_data(spark, df, sf).collect()}
    assert all(not plain_pii(t or "") or "[" in t for t in clean.values())
    mixed = p.mix(spark, df, sf)
    taken = {x.doc_id: x.taken for x in mix_sources(df).collect()}
    sizes = {}
    for x in mixed.collect():
        sizes[x.doc_id] = sizes.get(x.doc_id, 0) + len(words(x.text))
    assert {k: v for k, v in taken.items() if v} == {k: v for k, v in sizes.items() if v}


# ---------------------------------------------------------------- cases of round 2


def naive_bayes(rows, text, buckets=langid.BUCKETS, smoothing=0.5):
    """Language and posterior by plain dictionaries."""

    def grams(t):
        low = f" {t.lower()} "
        c = [48 if 48 <= ord(x) <= 57 else 32 if ord(x) <= 32 else ord(x) for x in low]
        for n in langid.GRAMS:
            for i in range(len(c) - n + 1):
                h = 0
                for x in c[i : i + n]:
                    h = (h * 0x01000193 & 0xFFFFFFFF) ^ x
                m = ((h ^ (n * 0x9E3779B1 & 0xFFFFFFFF)) * 0x85EBCA6B) & 0xFFFFFFFF
                yield ((m ^ (m >> 15)) * 0xC2B2AE35 & 0xFFFFFFFF) >> (32 - buckets.bit_length() + 1)

    count, docs_ = {}, {}
    for t, lang in rows:
        if t and lang and any(map(str.isalpha, t)):
            docs_[lang] = docs_.get(lang, 0) + 1
            for b in grams(t):
                count.setdefault(lang, {})[b] = count.setdefault(lang, {}).get(b, 0) + 1
    if not text or not any(map(str.isalpha, text)) or not docs_:
        return "und", 0.0
    score = {}
    for lang in sorted(docs_):
        total = sum(count[lang].values()) + smoothing * buckets
        score[lang] = np.log(docs_[lang] / sum(docs_.values())) + sum(np.log((count[lang].get(b, 0) + smoothing) / total) for b in grams(text))
    best = max(score, key=lambda x: (score[x], [-ord(c) for c in x]))
    return best, 1 / sum(np.exp(min(s - score[best], 50)) for s in score.values())


def test_language_equals_plain_counting(spark):
    import zlib

    texts = ["the cat and the dog", "der Hund und die Katze", "le chat et le chien", "½ ²", "Ⅷ", None, "", "12", "the dog", "die Katze", "x", "the cat and the dog", "ünd Ärger " * 40, "日本 x"]
    langs = ["en", "de", "fr", "en", None, "en", "fr", "de", "en", "de", None, "en", "de", "fr"]
    df = docs(spark, texts, langs=langs).withColumn("lang_pred", F.lit("clash")).withColumn("score", F.lit(7.0))
    known = [(t, x) for i, (t, x) in enumerate(zip(texts, langs, strict=True)) if zlib.crc32(str(i).encode()) % 5]
    for x in langid.identify(df).collect():
        lang, score = naive_bayes(known, texts[x.doc_id])
        assert x.lang_pred == lang and abs(x.score - score) < 1e-4, texts[x.doc_id]


def test_turns_of_any_size_hold_every_gram():
    texts = ["héllo Wörld 12", "", "a", "日本語 x" * 30, "½ ²"]

    def all_of(most):
        got = [[] for _ in texts]
        for who, many, b in langid.gram_buckets(texts, most=most):
            end = 0
            for w, m in zip(who, many, strict=True):
                got[w] += b[end : end + m].tolist()
                end += m
            assert end == len(b)
        return [sorted(x) for x in got]

    assert all_of(4) == all_of(7) == all_of(1 << 16)


def test_windows_in_any_turns_tell_sequences_apart(monkeypatch):
    from bspflow.llm import common, substring

    r = random.Random(1)
    texts = [None, "", " a b ".join(["x"] * 40)] + [" ".join(r.choice("abcd") for _ in range(n)) for n in (3, 49, 50, 51, 300, 2000)]
    whole = common.word_chunks
    for size, most in ((64, 100), (1 << 18, 1 << 16)):
        monkeypatch.setattr(substring, "word_chunks", lambda data, size=size: whole(data, size))
        for w in (3, 50):
            of, n = {}, 0
            got = {(d, p): (a, b) for turn in substring.Windows(w, True, most).of(texts) for a, b, d, p in zip(*(x.tolist() for x in turn), strict=True)}
            for i, t in enumerate(texts):
                ws = (t or "").split()
                for j in range(len(ws) - w + 1):
                    n += 1
                    assert of.setdefault(tuple(ws[j : j + w]), got[i, j]) == got[i, j]
            assert n == len(got) and len(set(of.values())) == len(of)
        for t in filter(None, texts):
            ws = t.encode().split()
            cuts = sorted(r.sample(range(len(ws) + 1), 4)) if len(ws) > 3 else [0, 0, 0, 0]
            begin, end = np.array(cuts[::2]), np.array(cuts[1::2])
            left = [x for i, x in enumerate(ws) if not any(a <= i < b for a, b in zip(begin, end, strict=True))]
            assert substring._keep_words(t.encode(), begin, end) == (len(ws), b" ".join(left).decode())


def test_rows_that_repeat_are_cut_alike(spark):
    shared = " ".join(f"w{i}" for i in range(120))
    df = docs(spark, [shared, f"head {shared} tail", "few words"]).withColumn("low", F.lit(1)).withColumn("hits", F.lit(2))
    many = df.union(df).union(df)
    got = sorted((x.doc_id, x.n_words, x.n_removed, x.kept_text) for x in substring_dedup(many).collect())
    assert got == sorted([(0, 120, 0, shared), (1, 122, 120, "head tail"), (2, 2, 0, "few words")] * 3)


def test_fingerprints_in_any_turns(monkeypatch):
    import xxhash

    from bspflow.llm import common

    r = random.Random(2)

    def plainly(t):
        w = (t or "").encode().lower().split()
        hashes = [xxhash.xxh64_intdigest(b" ".join(w[i : i + 4]), 42) for i in range(len(w) - 3)] or ([xxhash.xxh64_intdigest(b" ".join(w), 42)] if w else [])
        return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))

    texts = [None, "", " ", "A b", "a B C d", "É a b c d"] + [" ".join(r.choice(["Ab", "c", "dé", "E"]) for _ in range(n)) for n in (1, 2, 3, 4, 5, 9, 300, 301)]
    whole = common.word_chunks
    for size, most in ((3, 5), (16, 1 << 16), (1 << 18, 5)):
        monkeypatch.setattr(simhash, "word_chunks", lambda data, size=size: whole(data, size))
        assert simhash.fingerprints(texts, most=most).tolist() == [plainly(t) for t in texts]


def test_index_finds_every_close_pair_and_no_other(spark):
    r = random.Random(3)
    base = [r.getrandbits(64) for _ in range(40)]
    prints = set(base)
    for b in base:
        for bits in (1, 3, 4, 5, 8):
            x = b
            for k in r.sample(range(64), bits):
                x ^= 1 << k
            prints.add(x)
    prints |= {base[0] ^ (k << 24) for k in range(60)}  # many that share five bytes
    prints = sorted(prints)
    rows = spark.createDataFrame([(x - (1 << 64) if x >> 63 else x,) for x in prints], "fp long")
    lead = {x: x for x in prints}

    def top(links, of):
        def find(x):
            while of[x] != x:
                x = of[x]
            return x

        for a, b in links:
            of[find(a)] = find(b)
        groups = {}
        for x in of:
            groups.setdefault(find(x), set()).add(x)
        return sorted(map(sorted, groups.values()))

    want = top([(a, b) for i, a in enumerate(prints) for b in prints[:i] if (a ^ b).bit_count() <= 4], dict(lead))
    for most in (4096, 8, 2):
        links = [(x.a & (1 << 64) - 1, x.b & (1 << 64) - 1) for x in simhash.simhash_links(rows, most=most).collect()]
        assert top(links, dict(lead)) == want, most


def test_samples_do_not_depend_on_kept_words():
    pieces = spiece.Pieces(open(queries.piece_model(), "rb").read())
    texts = ["the cat sat", None, "", "  two  spaces", "the dog and the cat sat on the mat", "naïve ▁ 日本", "the " * 50 + "end"]
    kept = spiece.Kept(pieces, ["the cat the cat sat sat on", None, ""])
    plainly = spiece.sample_batch(pieces, list(range(7)), texts, 3, 5)
    for a, b in zip(plainly, spiece.sample_batch(pieces, list(range(7)), texts, 3, 5, kept), strict=True):
        assert [x[0].tolist() for x in a] == [x[0].tolist() for x in b]
        assert np.allclose([x[1:] for x in a], [x[1:] for x in b])
    assert all(spiece._decodes(pieces, x[0], t) for of, t in zip(plainly, texts, strict=True) for x in of)


def test_piece_ids_of_runs_are_those_of_the_whole(spark):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=queries.piece_model())
    texts = ["abc def  ghi", "", None, " x " * 500, "é ü " * 900 + " end", "abc def  ghi"]
    for run_chars in (5, 1 << 16):
        got = tokens_out.piece_tokens(docs(spark, texts), queries.piece_model(), run_chars).collect()
        assert [None if x.tokens is None else np.frombuffer(x.tokens, "<u2").tolist() for x in sorted(got, key=lambda x: x.doc_id)] == [None if t is None else sp.encode(t) for t in texts]


def test_a_slot_is_read_by_a_seek_and_broken_shards_are_refused(spark):
    path = shared_path(spark, "seek")
    ids = tokens_out.piece_tokens(docs(spark, ["some words here"] * 40 + [None]), queries.piece_model())
    m = tokens_out.write_training_order(ids, path, F.col("tokens"), length=8, width=2, end=b"\2\0", shard_rows=4)
    rows = {x.slot: bytes(x.tokens) for x in tokens_out.read_slots(spark, path).collect()}
    assert len(rows) == m["sequences"] and all(tokens_out.read_at(spark, path, s).tobytes() == rows[s] for s in (0, 5, m["sequences"] - 1))
    empty = shared_path(spark, "none")
    assert tokens_out.write_training_order(ids.limit(0), empty, F.col("tokens"), width=2, end=b"\2\0")["sequences"] == 0
    assert tokens_out.read_slots(spark, empty).count() == 0
    pieces = pa.RecordBatch.from_pydict({"slot": [0, 1, 1], "at": [0, 0, 8], "piece": [b"12345678", b"12345678", b"12345678"]})
    with pytest.raises(RuntimeError):
        list(tokens_out._join_rows(16)(iter([pieces])))


def test_large_components_stay_whole_and_too_large_ones_raise(spark):
    rng = np.random.default_rng(3)
    for size in (3, 1 << 20, 1 << 29, 1 << 33):
        rows = rng.integers(-size, size, size=(200, 5))
        rows[7] = rows[9]
        ids = rng.permutation(1000)[:200].astype(np.int64)
        block = bitslice.Block(*bitslice.Block.build(ids, rows))
        for q in rng.integers(-min(size, 1 << 26), min(size, 1 << 26), size=(4, 5)):
            true = sorted((-sum(int(a) * int(b) for a, b in zip(row, q, strict=True)), int(i)) for row, i in zip(rows, ids, strict=True))[:20]
            assert sorted((-int(s), int(i)) for i, s in zip(*block.top(q, 20, None), strict=True)) == true
    make = lambda rows: spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    v = make([(0, [1.0, 0.0]), (1, [1e6, 0.0]), (2, [2e6, 0.0])])
    got = [(x.vec_id, x.score) for x in bitslice.exact_top_k(v, v.where("vec_id = 0"), 20).orderBy("rank").collect()]
    assert got == [(2, 8192000000), (1, 4096000000)]
    with pytest.raises(OverflowError):
        big = make([(0, [1e9, 0.0]), (1, [1e9, 0.0])])
        bitslice.exact_top_k(big, big, 1).collect()
    assert bitslice.exact_top_k(v.limit(0), v, 3).count() == 0


def test_forest_recall_with_leaves_of_few_rows(spark):
    rng = np.random.default_rng(4)
    centres = rng.normal(size=(30, 16))
    x = centres[rng.integers(0, 30, 3000)] + 0.3 * rng.normal(size=(3000, 16))
    df = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
    got = ann.nearest(df, df.where("vec_id % 20 = 0"), k=10).toPandas().groupby("query_id").vec_id.apply(set)
    scores = x[::20] @ x.T
    scores[np.arange(150), np.arange(0, 3000, 20)] = -np.inf
    true = np.argsort(-scores, axis=1)[:, :10]
    assert np.mean([len(got[20 * i] & set(t.tolist())) / 10 for i, t in enumerate(true)]) >= 0.9


def test_one_of_two_writers_enters_a_batch(spark):
    one = spark.createDataFrame([(1, "a", "en", "w", 5)], "doc_id long, source string, lang string, tokenizer string, tokens long")
    ledger = rollup.Ledger(spark, shared_path(spark, "race"))
    assert ledger.commit("b", rollup.signed_changes(None, one)) and not ledger._enter("b", "/" + "0" * 32)
    assert ledger.commit("none", rollup.signed_changes(None, one.limit(0)))
    assert [(x.docs, x.tokens) for x in ledger.totals().collect()] == [(1, 5)]


def test_a_very_long_text_goes_through(spark):
    r = random.Random(5)
    long = " ".join("".join(r.choice("abcdefgh") for _ in range(6)) for _ in range(400_000))
    df = docs(spark, [long, long, "short text"], langs=["en"] * 3)
    assert [(x.n_words, x.n_removed) for x in substring_dedup(df).orderBy("doc_id").collect()] == [(400_000, 0), (400_000, 400_000), (2, 0)]
    assert [x.component_id for x in simhash.near_duplicate_components(df).orderBy("doc_id").collect()] == [0, 0, 2]
    assert langid.identify(df).where("lang_pred = 'en'").count() == 3


def test_near_copies_leave_one_row_of_each_group(spark):
    import corpus_pipeline as p

    one, two, three = " ".join(f"a{i}" for i in range(60)), " ".join(f"b{i}" for i in range(60)), " ".join(f"c{i}" for i in range(60))
    # id 2 is a copy in one row and clean in another; id 3 repeats; texts without an id are copies, and a group of their own
    rows = [(1, one), (2, one), (2, two), (3, three), (3, three), (None, one), (None, "x y z q w"), (None, "x y z q w"), (9, None), (7, ""), (8, " ")]
    df = spark.createDataFrame([(i, t, "en", "s", 1, 5) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long, component long")
    got = p.drop_near_copies(spark, df, "")
    assert got.columns == list(p.COLUMNS)
    want = [(1, one), (2, two), (3, three), (7, ""), (None, "x y z q w")]
    key = lambda x: (x[0] is None, x[0] or 0, x[1])
    assert sorted(((x.doc_id, x.text) for x in got.collect()), key=key) == sorted(want, key=key)
    assert p.drop_near_copies(spark, df.limit(0), "").count() == 0


def test_spiece_slices_share_the_room_after_kept_words():
    import numpy as np

    from bspflow.llm import spiece
    from bspflow.llm.queries import piece_model

    with open(piece_model(), "rb") as f:
        pieces = spiece.Pieces(f.read())
    texts = [["the cat and the dog", "a house"], ["the dog sat on the café 世", "and the cat and another cat"], ["the end"]]
    kept = spiece.Kept(pieces, [t for part in texts for t in part])
    one, two = (spiece.Lattice(pieces, [f" {w}"], kept.lattice) for w in ("another", "sat"))
    assert np.shares_memory(one.log_p, two.log_p)
    for n, part in enumerate(texts):
        got = spiece.sample_batch(pieces, [n] * len(part), part, 2, 11, kept)
        alone = spiece.sample_batch(pieces, [n] * len(part), part, 2, 11)
        for a, b in zip(got, alone, strict=True):
            assert [x[0].tolist() for x in a] == [x[0].tolist() for x in b]
            assert np.allclose([x[1:] for x in a], [x[1:] for x in b])
