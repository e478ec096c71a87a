"""A scalar, an aggregate and a table function around the methods."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udf, pandas_udf, udf, udtf


@pandas_udf("string")
def canonical_url(url: pd.Series) -> pd.Series:
    """Lower case, without the scheme."""
    return url.str.replace("^https?://", "", regex=True).str.lower()


@arrow_udf("string")
def canonical_url_arrow(url: pa.Array) -> pa.Array:
    """The same on Arrow arrays."""
    return pc.utf8_lower(pc.replace_substring_regex(url, pattern="^https?://", replacement=""))


@udf("long")
def tie_break(a: int, b: int) -> int:
    """Of two ids the one that is smaller modulo 97, then the smaller: a row at a time, for rules that columns can't say."""
    return min((a, b), key=lambda v: (v % 97, v))


@pandas_udf("long")
def tree_min(v: pd.Series) -> int:
    """The smallest value, as a grouped aggregate."""
    return int(v.min())


@udtf(returnType="i bigint, kmer string")
class Kmers:
    """The substrings of length k of a text."""

    def eval(self, text: str, k: int) -> Iterator[tuple[int, str]]:
        for i in range(len(text or "") - k + 1):
            yield i, text[i : i + k]


@udtf(returnType="dst bigint, weight bigint")
class Neighbors:
    """The edges of a nested vertex, one row each."""

    def eval(self, edges: list) -> Iterator[tuple[int, int]]:
        for e in edges or []:
            yield e["dst"], e["value"]


def register(spark: SparkSession) -> None:
    """Make the functions callable from SQL."""
    spark.udf.register("bspflow_canonical_url", canonical_url)
    spark.udf.register("bspflow_canonical_url_arrow", canonical_url_arrow)
    spark.udf.register("bspflow_tie_break", tie_break)
    spark.udf.register("bspflow_tree_min", tree_min)
    spark.udtf.register("bspflow_kmers", Kmers)
    spark.udtf.register("bspflow_neighbors", Neighbors)
