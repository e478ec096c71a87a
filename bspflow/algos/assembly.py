"""De Bruijn graphs of text reads and their cleaning: tips, bubbles, low coverage, bridges, small parts, merged paths."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graphs import table
from . import compact
from .structure import cut, kept, min_label


def reads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct lines of English documents, lower-cased, letters a to z only.

    Other languages are left out as their letters are.
    """
    docs = table(spark, sf_dir, "documents").where("lang = 'en'")
    lines = docs.select(F.explode(F.split("text", "\n")).alias("line"))
    return lines.select(F.regexp_replace(F.lower("line"), "[^a-z]", "").alias("read")).distinct()


def kmers(read: DataFrame, k: int = 12) -> DataFrame:
    """(kmer, next): the k-mers of each read, each with the one after it."""
    some = read.where(F.char_length("read") >= k).withColumn("n", F.char_length("read") - k + 1)
    at = some.select("read", "n", F.explode(F.sequence(F.lit(1), F.col("n"))).alias("i"))
    piece = lambda i: F.substring(F.col("read"), i, F.lit(k))
    return at.select(piece(F.col("i")).alias("kmer"), F.when(F.col("i") < F.col("n"), piece(F.col("i") + 1)).alias("next"))


def debruijn(read: DataFrame, k: int = 12) -> tuple[DataFrame, DataFrame]:
    """``nodes``(kmer, coverage) and ``edges``(src, dst, coverage) keyed by the k-mers themselves."""
    at = kmers(read, k)
    nodes = at.groupBy("kmer").agg(F.count("*").alias("coverage"))
    edges = at.where("next IS NOT NULL").groupBy(F.col("kmer").alias("src"), F.col("next").alias("dst")).agg(F.count("*").alias("coverage"))
    return nodes, edges


def unitigs(nodes: DataFrame, edges: DataFrame, most_rounds: int = 40) -> tuple[DataFrame, DataFrame]:
    """Merge unbranched paths: ``units``(uid, head, tail, seq, coverage, n) and ``links``(src, dst) between units.

    An edge is inside a path if it is its source's only out-edge and its target's only in-edge.  Nodes find their
    path's head by pointer doubling; cycles are cut at their smallest node.
    """
    nodes, edges = cut(nodes), cut(edges)
    one_out = edges.groupBy("src").agg(F.count("*").alias("n"), F.min("dst").alias("dst")).where("n = 1").select("src", "dst")
    one_in = edges.groupBy("dst").agg(F.count("*").alias("n")).where("n = 1").select("dst")
    inner = cut(one_out.join(one_in, "dst").where("src <> dst").select("src", "dst"))
    at = cut(nodes.join(inner.select(F.col("dst").alias("kmer"), F.col("src").alias("prev")), "kmer", "left").select("kmer", "prev", F.when(F.col("prev").isNull(), 0).otherwise(1).cast("long").alias("back"), F.least("kmer", F.coalesce("prev", "kmer")).alias("low")))
    open_, n_nodes = True, nodes.count()
    for _ in range(most_rounds):
        jump = at.select(F.col("kmer").alias("prev"), F.col("prev").alias("pp"), F.col("back").alias("b"), F.col("low").alias("l"))
        at = cut(at.join(jump, "prev", "left").select("kmer", F.when(F.col("pp").isNull(), F.col("prev")).otherwise(F.col("pp")).alias("prev"), (F.col("back") + F.coalesce("b", F.lit(0))).alias("back"), F.least("low", F.coalesce("l", "low")).alias("low"), F.col("pp").isNull().alias("ended")))
        left = at.where("NOT ended").agg(F.count("*"), F.min("back")).first()
        open_ = left[0] > 0
        if not open_ or left[1] > n_nodes:
            break
    ring = at.where("NOT ended").select("low").distinct()
    if open_:  # cycles: name by the smallest node and rank from it by walking along a cut list
        inner2 = inner.join(ring.select(F.col("low").alias("dst")), "dst", "left_anti")
        from .structure import list_rank

        ids = cut(nodes.select("kmer"))
        ranked = list_rank(ids.join(inner2.select(F.col("dst").alias("kmer"), F.col("src").alias("prev")), "kmer", "left").select(F.xxhash64("kmer").alias("vid"), F.when(F.col("prev").isNotNull(), F.xxhash64("prev")).alias("next")))
        back = ids.withColumn("vid", F.xxhash64("kmer")).join(ranked, "vid").select("kmer", F.col("rank").alias("back2"))
        at = cut(at.join(back, "kmer").select("kmer", F.when(F.col("ended"), F.coalesce("prev", "kmer")).otherwise(F.col("low")).alias("head"), F.when(F.col("ended"), F.col("back")).otherwise(F.col("back2")).alias("back")))
    else:
        at = at.select("kmer", F.coalesce("prev", "kmer").alias("head"), "back")
    rows = at.join(nodes, "kmer").groupBy("head").agg(F.array_sort(F.collect_list(F.struct("back", "kmer"))).alias("path"), F.sum("coverage").alias("coverage"), F.count("*").alias("n"))
    last = F.element_at("path", -1)["kmer"]
    letters = F.array_join(F.transform(F.slice("path", 2, 1_000_000_000), lambda x: F.substring(x["kmer"], -1, 1)), "")
    units = cut(rows.select("head", last.alias("tail"), F.concat(F.element_at("path", 1)["kmer"], letters).alias("seq"), "coverage", "n"))
    links = edges.join(inner, ["src", "dst"], "left_anti")
    links = links.join(units.select(F.col("tail").alias("src"), F.col("head").alias("su")), "src").join(units.select(F.col("head").alias("dst"), F.col("head").alias("du")), "dst")
    return units, cut(links.select(F.col("su").alias("src"), F.col("du").alias("dst")).distinct())


def _tips(units: DataFrame, links: DataFrame, k: int) -> DataFrame:
    """(head) of units that end dead on one side, are shorter than 2k, and have less mean coverage than a rival at the other side."""
    mean = F.col("coverage") / F.col("n")
    u = units.withColumn("mean", mean)
    has_in, has_out = links.select(F.col("dst").alias("head")).distinct(), links.select(F.col("src").alias("head")).distinct()
    short = u.where(F.char_length("seq") < 2 * k)
    ends = short.join(has_out, "head", "left_anti").join(has_in, "head", "left_semi")
    starts = short.join(has_in, "head", "left_anti").join(has_out, "head", "left_semi")
    into = ends.select("head", "mean").join(links.select("src", F.col("dst").alias("head")), "head").join(links.toDF("src", "rival"), "src").where("rival <> head")
    onto = starts.select("head", "mean").join(links.select(F.col("src").alias("head"), "dst"), "head").join(links.toDF("rival", "dst"), "dst").where("rival <> head")
    rivals = into.select("head", "mean", "rival").union(onto.select("head", "mean", "rival")).join(u.select(F.col("head").alias("rival"), F.col("mean").alias("other")), "rival")
    return rivals.where("mean < other OR (mean = other AND head > rival)").select("head").distinct()


def remove_tips(units: DataFrame, links: DataFrame, k: int = 12) -> DataFrame:
    """Units that end dead on one side, are shorter than 2k, and have less mean coverage than a rival at the other side, go."""
    return units.join(_tips(units, links, k), "head", "left_anti")


def _bubbles(units: DataFrame, links: DataFrame, most_edits: int = 4) -> DataFrame:
    inside = links.groupBy(F.col("dst").alias("head")).agg(F.count("*").alias("n"), F.min("src").alias("a")).where("n = 1").select("head", "a")
    outside = links.groupBy(F.col("src").alias("head")).agg(F.count("*").alias("n"), F.min("dst").alias("b")).where("n = 1").select("head", "b")
    arms = units.join(inside, "head").join(outside, "head").withColumn("mean", F.col("coverage") / F.col("n"))
    best = arms.groupBy("a", "b").agg(F.count("*").alias("arms"), F.max(F.struct("mean", "head", "seq")).alias("best")).where("arms > 1")
    return arms.join(best, ["a", "b"]).where((F.col("head") != F.col("best.head")) & (F.levenshtein(F.col("seq"), F.col("best.seq")) <= most_edits)).select("head")


def pop_bubbles(units: DataFrame, links: DataFrame, most_edits: int = 4) -> DataFrame:
    """Of parallel units between the same two units, those within ``most_edits`` of the best covered one go."""
    return units.join(_bubbles(units, links, most_edits), "head", "left_anti")


def drop_low_coverage(nodes: DataFrame, edges: DataFrame, least: int = 2) -> tuple[DataFrame, DataFrame]:
    """Nodes seen fewer than ``least`` times go, with their edges."""
    kept = nodes.where(F.col("coverage") >= least)
    names = kept.select("kmer")
    return kept, edges.join(names.toDF("src"), "src", "left_semi").join(names.toDF("dst"), "dst", "left_semi")


def _bridges(units: DataFrame, links: DataFrame, most: int = 16, long: int = 40) -> DataFrame:
    size = units.select(F.col("head").alias("x"), F.char_length("seq").alias("len"))
    before = links.join(size, links["src"] == size["x"]).groupBy(F.col("dst").alias("head")).agg(F.min("len").alias("low_in"))
    after = links.join(size, links["dst"] == size["x"]).groupBy(F.col("src").alias("head")).agg(F.min("len").alias("low_out"))
    return units.where(F.char_length("seq") <= most).join(before, "head").join(after, "head").where((F.col("low_in") >= long) & (F.col("low_out") >= long)).select("head")


def remove_bridges(units: DataFrame, links: DataFrame, most: int = 16, long: int = 40) -> DataFrame:
    """Short units whose neighbours on both sides are all long go."""
    return units.join(_bridges(units, links, most, long), "head", "left_anti")


def drop_small_components(nodes: DataFrame, edges: DataFrame, least: int = 20) -> DataFrame:
    """Nodes of components with fewer than ``least`` nodes go."""
    ids = nodes.select(F.xxhash64("kmer").alias("vid"))
    label = min_label(edges.select(F.xxhash64("src").alias("src"), F.xxhash64("dst").alias("dst")), ids)
    big = label.groupBy("label").agg(F.count("*").alias("n")).where(F.col("n") >= least).select("label")
    kept = label.join(big, "label").select("vid")
    return nodes.withColumn("vid", F.xxhash64("kmer")).join(kept, "vid", "left_semi").drop("vid")


def read_units(read: DataFrame, k: int = 12, with_links: bool = True) -> tuple[DataFrame, DataFrame]:
    """``unitigs`` of reads of 0-9 and a-z, without a table of k-mers; heads are numbers in the order of the k-mers."""
    return compact.units_of(compact.chunks(read, k), k, with_links)


def clean_reads(read: DataFrame, pattern: str, k: int = 12) -> DataFrame:
    """(head, seq, coverage, n): ``read_units`` less 'tips', 'bubbles' or 'bridges'."""
    doubtful, step = {
        "tips": (compact.tips, lambda u, l: remove_tips(u, l, k)),
        "bubbles": (compact.arms, pop_bubbles),
        "bridges": (compact.bridges(), remove_bridges),
    }[pattern]
    return compact.cleaned(compact.chunks(read, k), k, doubtful, step)


def clean_chain(read: DataFrame, k: int = 12, rounds: int = 1) -> DataFrame:
    """The six patterns one after another, ``rounds`` times, then merged paths: (head, seq, coverage, n).

    K-mers seen once are cut out of the reads; the other patterns take units away and join what no longer branches.
    Counts stay as they are when others go, so later rounds have no rare k-mers to drop.
    """
    (held,) = kept(lambda: (compact.without_rare(compact.chunks(read, k), k),))
    units, links = kept(lambda: tuple(cut(x) for x in compact.units_of(held, k)), (held,))
    for left in range(rounds - 1, -1, -1):
        for gone in (lambda u, l: _tips(u, l, k), _bubbles, _bridges):
            units, links = kept(lambda of=gone, u=units, l=links: compact.compact(u, l, of(u, l), k), (units, links))
        big = lambda u=units, l=links: cut(compact.without_small(u, l, 20))
        if left:
            there = lambda u, l=links: cut(l.join(u.select(F.col("head").alias("src")), "src", "left_semi").select("src", "dst"))
            units, links = kept(lambda: ((u := big()), there(u)), (units, links))
        else:
            (units,) = kept(lambda: (big(),), (units, links))
    return units.select(F.substring("seq", 1, k).alias("head"), "seq", "coverage", "n")
