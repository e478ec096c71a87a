"""De Bruijn graphs: paths, cycles, tips and bubbles on short reads."""

from bspflow.algos import assembly


def reads(spark, *rows):
    return spark.createDataFrame([(r,) for r in rows], "read string")


def test_a_read_without_repeats_is_one_unit(spark):
    nodes, edges = assembly.debruijn(reads(spark, "abcdefghij"), k=4)
    units, links = assembly.unitigs(nodes, edges)
    assert [r.seq for r in units.collect()] == ["abcdefghij"] and links.count() == 0


def test_a_cycle_is_cut_at_its_smallest_node(spark):
    nodes, edges = assembly.debruijn(reads(spark, "abcdeabcd"), k=4)
    units, _ = assembly.unitigs(nodes, edges)
    assert [r.seq for r in units.collect()] == ["abcdeabc"]


def test_tip_and_bubble(spark):
    nodes, edges = assembly.debruijn(reads(spark, *["abcdefghijklmnop"] * 3, "abcdefgh0", "abcdefg1ijklmnop"), k=4)
    units, links = assembly.unitigs(nodes, edges)
    seqs = {r.seq for r in assembly.remove_tips(units, links, 4).collect()}
    assert not any(s.endswith("0") for s in seqs)
    kept = {r.seq for r in assembly.pop_bubbles(units, links, 9).collect()}
    assert any("h" in s for s in kept)


def test_long_documents_and_lines_are_read_whole(spark, tmp_path):
    import random
    from collections import Counter

    from bspflow.workloads import QUERIES

    r = random.Random(4)
    lines = ["".join(r.choice("abcd") for _ in range(n)) for n in (3000, 240, 11, 12)]
    spark.createDataFrame([(1, "\n".join(lines), "en", 3266), (2, lines[1], "en", 240)], "doc_id long, text string, lang string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    want = Counter(t[i : i + 12] for t in lines for i in range(len(t) - 11))
    assert {x.kmer: x.coverage for x in QUERIES["w_debruijn"](spark, str(tmp_path)).collect()} == want
    units = QUERIES["w_merge_debruijn"](spark, str(tmp_path)).collect()
    assert sum(x.coverage for x in units) == sum(want.values())


def _restrict(units, nodes, edges, k):
    from pyspark.sql import functions as F

    inside = units.select(F.explode(F.transform(F.sequence(F.lit(1), F.char_length("seq") - k + 1), lambda i: F.substring(F.col("seq"), i, F.lit(k)))).alias("kmer")).distinct()
    names = inside.select("kmer")
    return nodes.join(inside, "kmer", "left_semi"), edges.join(names.toDF("src"), "src", "left_semi").join(names.toDF("dst"), "dst", "left_semi")


def _some_reads():
    """Reads that branch, end inside paths, go round in cycles and hold runs of one letter, one much longer than a chunk."""
    import random

    r = random.Random(7)
    genome = "".join(r.choice("abcd") for _ in range(1500))
    rows = [genome[i : i + r.randrange(5, 90)] for i in (r.randrange(1400) for _ in range(120))] + [genome[200:1300]]
    rows += ["".join(c if r.random() > 0.03 else r.choice("abcd") for c in x) for x in rows[:60]]
    return sorted({*rows, "xyzw" * 6 + "xyzwx", "zwxyzwxyzw", "mmmmmmmmm", "mmmmmmmmn", "uvuvuvuvuv", "pqrstuv", "short"})


def test_units_of_reads_in_small_chunks_equal_those_of_the_k_mer_tables(spark, monkeypatch):
    from pyspark.sql import functions as F

    from bspflow.algos import compact

    monkeypatch.setattr(compact, "CHUNK", 400)
    monkeypatch.setattr(compact, "PART", 800)
    read, k = reads(spark, *_some_reads()), 7
    units, links = assembly.unitigs(*assembly.debruijn(read, k))
    got, met = assembly.read_units(read, k)
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(got.select(F.substring("seq", 1, k), "seq", "coverage", "n")) == rows(units.select("head", "seq", "coverage", "n"))
    name = lambda df, c: df.join(got.select(F.col("head").alias(c), F.substring("seq", 1, k).alias(f"{c}_name")), c)
    assert rows(name(name(met, "src"), "dst").select("src_name", "dst_name")) == rows(links)
    for step in (lambda u, l: assembly.remove_tips(u, l, k), assembly.pop_bubbles, lambda u, l: assembly.remove_bridges(u, l, 9, 12)):
        assert {x.seq for x in step(got, met).collect()} == {x.seq for x in step(units, links).collect()}


def test_chains_and_cycles_get_one_label_each_in_one_task_and_in_rounds(spark, monkeypatch):
    from bspflow.algos import compact

    links = [(5, 3), (3, 9), (9, 1), (20, 21), (21, 22), (22, 20), (40, 40)]
    soft = spark.createDataFrame(links, "src long, dst long")
    pieces = spark.createDataFrame([(v, f"{v:02d}", 1, 1) for v in (5, 3, 9, 1, 20, 21, 22, 40, 7)], "head long, seq string, coverage long, n long")
    for few in (0, 100):
        monkeypatch.setattr(compact, "FEW", few)
        whole, glued = compact.glue(pieces, soft, 1)
        assert [r.head for r in whole.collect()] == [7] and sorted(r.n for r in glued.collect()) == [1, 3, 4]


def test_small_components_without_a_row_for_each_link(spark, monkeypatch):
    from bspflow.algos import compact

    monkeypatch.setattr(compact, "CHUNK", 400)
    monkeypatch.setattr(compact, "PART", 800)
    read = reads(spark, *_some_reads())
    for least in (3, 8, 30):
        want = assembly.drop_small_components(*assembly.debruijn(read, 7), least)
        assert sorted(map(tuple, compact.big_components(read, 7, least).collect())) == sorted(map(tuple, want.collect()))


def test_clean_chain_equals_its_steps_on_k_mer_tables(spark, monkeypatch):
    from bspflow.algos import compact

    monkeypatch.setattr(compact, "CHUNK", 400)
    monkeypatch.setattr(compact, "PART", 800)
    read, k = reads(spark, *_some_reads()), 7
    nodes, edges = assembly.drop_low_coverage(*assembly.debruijn(read, k))
    for step in (lambda u, l: assembly.remove_tips(u, l, k), assembly.pop_bubbles, assembly.remove_bridges):
        nodes, edges = (assembly.cut(x) for x in _restrict(step(*assembly.unitigs(nodes, edges)), nodes, edges, k))
    nodes = assembly.cut(assembly.drop_small_components(nodes, edges))
    edges = edges.join(nodes.select(nodes.kmer.alias("src")), "src", "left_semi")
    units, _ = assembly.unitigs(nodes, edges)
    want = sorted(map(tuple, units.select("head", "seq", "coverage", "n").collect()))
    assert want and sorted(map(tuple, assembly.clean_chain(read, k).collect())) == want


def test_units_less_a_pattern_equal_the_step_on_k_mer_tables(spark, monkeypatch):
    from pyspark.sql import functions as F

    from bspflow.algos import compact

    monkeypatch.setattr(compact, "PART", 800)
    read, k = reads(spark, *_some_reads()), 7
    units, links = assembly.unitigs(*assembly.debruijn(read, k))
    held = compact.chunks(read, k)
    steps = {
        "tips": (compact.tips, lambda u, l: assembly.remove_tips(u, l, k)),
        "bubbles": (compact.arms, lambda u, l: assembly.pop_bubbles(u, l, 9)),
        "bridges": (compact.bridges(9, 12), lambda u, l: assembly.remove_bridges(u, l, 9, 12)),
    }
    for pattern, (doubtful, step) in steps.items():
        want = {tuple(r) for r in step(units, links).select("head", "seq", "coverage", "n").collect()}
        assert len(want) < units.count(), pattern
        for size in (20, 4):  # a filter with room, and one in which every unit is in doubt
            got = compact.cleaned(held, k, doubtful, step, size).select(F.substring("seq", 1, k), "seq", "coverage", "n").collect()
            assert len(got) == len(want) and {tuple(r) for r in got} == want, (pattern, size)


def test_units_that_surely_stay_are_in_no_table_of_a_cleaning_query(spark, tmp_path, monkeypatch):
    import random

    from bspflow.algos import compact
    from bspflow.workloads import QUERIES

    r = random.Random(5)
    words = ["".join(r.choice("abcdefgh") for _ in range(14)) for _ in range(60)]
    text = "\n".join("".join(r.choice(words) for _ in range(12)) for _ in range(80))
    spark.createDataFrame([(1, text, "en", len(text))], "doc_id long, text string, lang string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    rows, cut = [], compact.cut
    monkeypatch.setattr(compact, "cut", lambda df: rows.append((kept := cut(df)).where("seq IS NOT NULL" if "seq" in kept.columns else "false").count()) or kept)
    for query in ("w_clean_tips", "w_clean_bubbles", "w_clean_bridges"):
        rows.clear()
        assert QUERIES[query](spark, str(tmp_path)).count() > 2 * max(rows), query


def test_asks_with_keys_are_packed_and_told_once_if_a_key_is_twice(spark):
    import numpy as np
    import pyarrow as pa
    import pyarrow.compute  # noqa: F401

    from bspflow.algos import compact

    assert "key" not in compact.MARKED.names  # no row for each ask
    key = np.array([7, -3, 7, 5, -3, 7, 2**62], np.int64)
    left, right = np.arange(7), np.arange(7) + 100
    left[[2, 5]], right[[2, 5]], left[4], right[4] = left[0], right[0], left[1], right[1]
    found = set()
    rows = compact._dealt(key, left, right, 3)
    assert rows.num_rows <= 3 and rows["seq"].null_count == rows.num_rows
    for slot in set(rows["slot"].to_pylist()):
        got = compact._twice(rows.filter(pa.compute.equal(rows["slot"], slot)))
        found |= set(zip(got["left"].to_pylist(), got["right"].to_pylist()))
    assert found == {(0, 100), (1, 101)}
    assert compact._dealt(key[:0], left[:0], right[:0], 3).num_rows == 0


def test_what_a_step_takes_away_is_in_no_table_of_its_own(spark, monkeypatch):
    from bspflow.algos import compact

    held, made, cut = compact.chunks(reads(spark, *_some_reads()), 7), [], compact.cut
    monkeypatch.setattr(compact, "cut", lambda df: made.append(df.columns) or cut(df))
    compact.cleaned(held, 7, compact.tips, lambda u, l: assembly.remove_tips(u, l, 7))
    assert ["head"] not in made and ["head", "seq", "coverage", "n", "doubt"] in made


def test_a_chain_of_steps_keeps_no_table_that_its_result_does_not_read(spark):
    import os

    from bspflow.runtime.session import shared_folder

    folder = shared_folder(spark).removeprefix("file:")
    there = lambda: {x for x in os.listdir(folder) if x.startswith("cut-")}
    before = there()
    out = assembly.clean_chain(reads(spark, "abcdefghijklmnopqrstuvwxyzabcdefghijk", "abcdefghijklmnopqrstuvwxyzabcdefghijk", "abcdefgh0jklmnop"), 7)
    assert out.count() and there() - before == {f.split("/")[-2] for f in out.inputFiles()}


def test_units_of_small_components_go_by_neighbours_or_by_labels(spark, monkeypatch):
    import random

    from bspflow.algos import compact

    r = random.Random(4)
    units = [(v, r.choice((1, 1, 2, 3, 9))) for v in range(200)]
    links = sorted({(a, min(199, a + r.choice((0, 1, 1, 2)))) for a in r.sample(range(200), 110)})
    low = {v: v for v, _ in units}
    for _ in units:
        for a, b in links:
            low[a] = low[b] = min(low[a], low[b])
    size = {c: sum(n for v, n in units if low[v] == c) for c in low.values()}
    for few in (0, 1000):
        monkeypatch.setattr(compact, "FEW", few)
        for least in (3, 8, 20):
            got = compact.without_small(spark.createDataFrame(units, "head long, n long"), spark.createDataFrame(links, "src long, dst long"), least)
            assert {x.head for x in got.collect()} == {v for v, _ in units if size[low[v]] >= least}


def test_chains_and_cycles_that_begin_in_rounds_and_end_in_one_task(spark, monkeypatch):
    from bspflow.algos import compact

    chains = [list(range(a, a + n)) for a, n in ((100, 2), (200, 3), (300, 40), (400, 9))]
    rings = [list(range(a, a + n)) for a, n in ((500, 1), (600, 2), (700, 4), (800, 7))]
    links = [p for c in chains for p in zip(c, c[1:])] + [p for c in rings for p in zip(c, c[1:] + c[:1])]
    soft = spark.createDataFrame([(-b, -a) for a, b in links], "src long, dst long")
    for few in (20, 60):
        monkeypatch.setattr(compact, "FEW", few)
        got = {x.vid: x.label for x in compact._chain_labels(soft).collect()}
        assert sorted(got) == sorted(-v for c in chains + rings for v in c)
        for c in chains + rings:
            assert len({got[-v] for v in c}) == 1 and -got[-c[0]] in c
