"""The global state: one row, kept by the driver and stored durably with each checkpoint."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field

from pyspark.sql import SparkSession


@dataclass
class GlobalState:
    superstep: int = 1
    halt: bool = False
    aggregates: dict = field(default_factory=dict)

    def next(self, halt: bool, aggregates: dict) -> GlobalState:
        return GlobalState(self.superstep + 1, halt, aggregates)


class GlobalStateStore:
    """One JSON row a superstep under a folder of the distributed file system."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def write(self, gs: GlobalState) -> None:
        told = json.dumps(asdict(gs), default=str)
        self.spark.createDataFrame([(told,)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.path}/gs/{gs.superstep:08d}")

    def read(self, superstep: int) -> GlobalState:
        return GlobalState(**json.loads(self.spark.read.text(f"{self.path}/gs/{superstep:08d}").first()[0]))
