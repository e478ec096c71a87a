"""Mixing sources to target weights with DataFrame functions only.

Every document gets a hash-random key of its id and a seed.  Keys are uniform, so their leading bits deal each
source into ranges of even size; range totals and a running sum over ranges (thousands at most) give each range
its offset, and a running sum inside a range finishes the distributed prefix sum.  A source takes all its
documents as many whole epochs as its budget holds, and in the last epoch the documents in key order up to the
exact budget; the document on the cut gives its leading words.

Weights are whole numbers, dealt to sources in code point order (null last) and repeating.  Targets share the
total size by weight, stop at ``max_epochs`` times their source's size, and pass the excess on by weight.

Defined cases: null text has size 0; the null source is one source, last; an empty table or a table of empty
texts takes nothing; rows sharing an id share a key and are ordered by size; extra columns are ignored.
"""

from __future__ import annotations

from math import lcm

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import hash_key, materialize, plain, word_count

KEY_BITS = 60


def source_targets(sized: DataFrame, weights: tuple[int, ...] = (5, 2, 1), max_epochs: int = 3) -> DataFrame:
    """One row a source: its size, rows, target (double) and budget (whole words of the target).

    Sources are sorted by how soon they reach their limit; a source is held at its limit if what is left, shared
    by weight among it and those after it, reaches the limit.
    """
    many = lcm(*weights)
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_rows"))
    order = Window.orderBy(F.col("source").cast("binary").asc_nulls_last())
    turn = F.row_number().over(order) - 1
    weight = F.element_at(F.array(*[F.lit(w) for w in weights]), (turn % len(weights) + 1).cast("int")).cast("long")
    per = per.withColumn("turn", turn).withColumn("weight", weight)
    per = per.withColumn("cap", F.col("source_size") * max_epochs)
    by_limit = Window.orderBy(F.expr(f"cap * ({many} div weight)"), "turn")
    before, whole = by_limit.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    per = per.withColumn("total", F.sum("source_size").over(whole)).withColumn("all_weight", F.sum("weight").over(whole))
    wide = lambda c: F.col(c).cast("decimal(38,0)")
    per = per.withColumn("left", F.col("total") - F.coalesce(F.sum("cap").over(before), F.lit(0)))
    per = per.withColumn("left_weight", F.col("all_weight") - F.coalesce(F.sum("weight").over(before), F.lit(0)))
    per = per.withColumn("held", wide("cap") * wide("left_weight") <= wide("weight") * wide("left"))
    free = per.withColumn("rest", F.col("total") - F.coalesce(F.sum(F.when(F.col("held"), F.col("cap"))).over(whole), F.lit(0)))
    free = free.withColumn("rest_weight", F.sum(F.when(~F.col("held"), F.col("weight"))).over(whole))
    target = F.when(F.col("held"), F.col("cap").cast("double")).otherwise((F.col("weight") * F.col("rest")).cast("double") / F.col("rest_weight").cast("double"))
    budget = F.when(F.col("held"), F.col("cap")).otherwise(F.expr("weight * rest div rest_weight"))
    return free.select("source", "turn", "source_size", "n_rows", target.alias("target"), budget.cast("long").alias("budget"))


def mix_sources(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), max_epochs: int = 3, seed: int = 17, range_rows: int = 512, carry: tuple[str, ...] = ()) -> DataFrame:
    """How many words of each document the mix takes.

    Returns doc_id, source, size, source_size, target, taken, epochs (whole repeats) and cut (leading words taken
    once more), and the columns named by ``carry``.  Carried columns go with their row through the prefix sums, so
    wide ones move once and rows that share an id stay apart; a join of the result by id would multiply those.
    """
    if clash := {"size", "key", "turn", "range", "bits", "of", "target", "budget", "n_rows", "source_size", "offset", "before", "epochs", "cut", "taken"} & {c.lower() for c in carry}:
        raise ValueError(f"columns of the mix can't be carried: {sorted(clash)}")
    measures = [word_count(F.col("text")).alias("size"), hash_key(F.col("doc_id"), seed).alias("key")]
    sized = materialize(plain(docs, "doc_id", "source", "text").select("doc_id", "source", *measures), "sizes")
    told = source_targets(sized, weights, max_epochs)
    bits = F.least(F.greatest(F.ceil(F.log2(F.col("n_rows") / range_rows)), F.lit(0)), F.lit(16)).cast("int")
    told = materialize(told.withColumn("bits", bits), "targets")
    whole = plain(docs, "doc_id", "source", "text", *(c for c in carry if c != "text")).select("doc_id", "source", *measures, *carry) if carry else sized

    def ranged(rows: DataFrame) -> DataFrame:
        rows = rows.join(told.withColumnRenamed("source", "of"), F.col("source").eqNullSafe(F.col("of")))
        return rows.withColumn("range", F.expr(f"key div cast(pow(2, {KEY_BITS} - bits) as bigint)"))

    totals = ranged(sized).groupBy("turn", "range").agg(F.sum("size").alias("words"))
    running = Window.partitionBy("turn").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select("turn", "range", F.coalesce(F.sum("words").over(running), F.lit(0)).alias("offset"))
    ties = [F.xxhash64(*carry)] if carry else []
    inside = Window.partitionBy("turn", "range").orderBy("key", "doc_id", "size", *ties).rowsBetween(Window.unboundedPreceding, -1)
    placed = ranged(whole).join(offsets, ["turn", "range"]).withColumn("before", F.col("offset") + F.coalesce(F.sum("size").over(inside), F.lit(0)))
    placed = placed.withColumn("epochs", F.when(F.col("source_size") > 0, F.expr("budget div source_size")).otherwise(0))
    rest = F.col("budget") - F.col("epochs") * F.col("source_size")
    placed = placed.withColumn("cut", F.least(F.greatest(rest - F.col("before"), F.lit(0)), F.col("size")))
    taken = (F.col("epochs") * F.col("size") + F.col("cut")).cast("long")
    return placed.select("doc_id", "source", "size", "source_size", "target", taken.alias("taken"), F.col("epochs").cast("long").alias("epochs"), F.col("cut").cast("long").alias("cut"), *carry)
