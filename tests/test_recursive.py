"""Paths of the whole hierarchy of regions, nations, customers and suppliers."""

import duckdb

from bspflow.operators import relational


def test_paths_reach_every_customer_and_supplier_beyond_sparks_row_limit(spark, sf):
    before = spark.conf.get("spark.sql.cteRecursionRowLimit")
    spark.conf.set("spark.sql.cteRecursionRowLimit", "40")
    try:
        got = {tuple(r) for r in relational.o_sql_recursive(spark, sf).collect()}
    finally:
        spark.conf.set("spark.sql.cteRecursionRowLimit", before)
    t = lambda name: duckdb.sql(f"FROM read_parquet('{sf}/{name}.parquet')")
    up = dict(t("nation").project("n_nationkey, n_regionkey").fetchall())
    want = {(f"r{r}", f"root/r{r}", 1) for (r,) in t("region").project("r_regionkey").fetchall()}
    want |= {(f"n{n}", f"root/r{r}/n{n}", 2) for n, r in up.items()}
    for tag, name in (("c", "customer"), ("s", "supplier")):
        want |= {(f"{tag}{k}", f"root/r{up[n]}/n{n}/{tag}{k}", 3) for k, n in t(name).project(f"{tag}_{name[:4]}key, {tag}_nationkey").fetchall()}
    assert got == want
