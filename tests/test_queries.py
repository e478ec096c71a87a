"""The driver's contract: names, entry, and a sample of queries against their SQL."""

import glob
import os

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry_module

SAMPLE = ["w_pagerank_web", "w_cc_copy", "w_missing_vertex_web", "w_euler_region", "w_closure_reply", "w_mutation_conflict", "o_join_asof", "o_cube", "o_topk_group", "o_udtf", "s_session",
          "w_mutation_columns_conflict_left", "w_send_any_vertex_creates", "w_sssp_parents", "w_cc_hash_to_min", "o_apply_in_arrow", "o_sink_bucketed", "s_late"]


def rows(frame):
    frame = frame[sorted(frame.columns)]
    return sorted(tuple("-" if x is None or x != x else f"{x:.5f}" if isinstance(x, float) else str(x) for x in r) for r in frame.itertuples(index=False))


@pytest.fixture(scope="module")
def tables(sf):
    c = duckdb.connect()
    for f in glob.glob(f"{sf}/*.parquet"):
        c.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM read_parquet('{f}')")
    return c


def test_every_sql_has_a_query():
    assert set(entry_module.oracle_sql()) <= set(entry_module.queries())


def test_entry_gives_rows(spark):
    got = entry_module.entry(spark)
    assert got.columns == ["vid", "dist"] and got.count() > 0


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_its_sql(spark, sf, tables, name):
    # plain values: pandas would turn whole numbers beside nulls into floats on one side only
    found, told = entry_module.queries()[name](spark, sf), tables.sql(entry_module.oracle_sql()[name])
    got = pd.DataFrame([tuple(r) for r in found.collect()], columns=found.columns, dtype=object)
    want = pd.DataFrame(told.fetchall(), columns=told.columns, dtype=object)
    assert rows(got) == rows(want)


@pytest.mark.parametrize("system", ["process_mem", "gas", "mr_chain"])
def test_baselines_give_the_same_components(spark, sf, tables, system):
    test_query_equals_its_sql(spark, sf, tables, f"b_{system}_cc")
