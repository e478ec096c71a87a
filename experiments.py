"""Experiments on one machine: python experiments.py plans|connectors|throughput [sf_dir]; prints one JSON line.

plans        seconds of rank, distances and components under the full and the left-outer delivery join
connectors   seconds of rank under the four group-bys and connectors, by number of partitions
throughput   rank jobs an hour with one to three jobs at once
Speed-up and scale-up need machines: run ``bench.py`` with BENCH_CPUS and BENCH_SF_DIR set for each point.
"""

from __future__ import annotations

import json
import sys
import time

from pyspark.sql import SparkSession

from bspflow import graphs
from bspflow.algos import structure, vertex
from bspflow.model import Graph
from bspflow.plans.hints import Connector, GroupBy, Join, PlanHints, Store
from bspflow.runtime.pipeline import run_concurrent


def _graph(spark: SparkSession, sf: str, name: str) -> Graph:
    g = graphs.graph(spark, sf, name)
    return Graph(structure.cut(g.vertices), structure.cut(g.edges))


def _seconds(f) -> float:
    f()  # compiled code and page cache as in a running service
    began = time.time()
    f()
    return round(time.time() - began, 2)


def plans(spark: SparkSession, sf: str) -> dict:
    trade, cust, order = (_graph(spark, sf, n) for n in ("trade", "cust", "order"))
    source, took = vertex.highest_degree(cust), {}
    for join, store in ((Join.FULL, Store.SNAPSHOT), (Join.LEFT, Store.DELTA_LOG)):
        h = PlanHints(join, GroupBy.HASH, store=store)
        took[f"rank_{join.value}"] = _seconds(lambda: vertex.pagerank(trade, 5, fixed_point=True, hints=h))
        took[f"distances_{join.value}"] = _seconds(lambda: vertex.sssp(cust, source, hints=h))
        took[f"components_{join.value}"] = _seconds(lambda: vertex.connected_components(order, h))
    return took


def connectors(spark: SparkSession, sf: str) -> dict:
    trade, took = _graph(spark, sf, "trade"), {}
    for p in (4, 8, 32):
        for g in GroupBy:
            for c in Connector:
                took[f"{g.value}_{c.value}_{p}"] = _seconds(lambda: vertex.pagerank(trade, 5, fixed_point=True, hints=PlanHints(Join.FULL, g, c, partitions=p)))
    return took


def throughput(spark: SparkSession, sf: str) -> dict:
    trade, took = _graph(spark, sf, "trade"), {}
    job = lambda: vertex.pagerank(trade, 5, fixed_point=True)
    job()
    for at_once in (1, 2, 3):
        began = time.time()
        run_concurrent([job] * 6, at_once)
        took[f"jobs_an_hour_{at_once}"] = round(6 * 3600 / (time.time() - began), 1)
    return took


def main() -> None:
    name, sf = sys.argv[1], sys.argv[2] if len(sys.argv) > 2 else "/root/testdata/sf0.1"
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    print(json.dumps({"experiment": name, "sf": sf, "seconds": {"plans": plans, "connectors": connectors, "throughput": throughput}[name](spark, sf)}))


if __name__ == "__main__":
    main()
