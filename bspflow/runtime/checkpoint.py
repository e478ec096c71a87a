"""Durable checkpoints at superstep boundaries: state, messages and global state, then a manifest.

A checkpoint without its manifest is torn and is never read.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from .gs import GlobalState, GlobalStateStore


@dataclass
class Checkpointer:
    spark: SparkSession
    path: str

    def save(self, gs: GlobalState, state: DataFrame, msg: DataFrame) -> None:
        """State and messages as they are when ``gs.superstep`` is about to run."""
        at = f"{self.path}/ckpt/s={gs.superstep:08d}"
        state.write.mode("overwrite").parquet(f"{at}/vertex")
        msg.write.mode("overwrite").parquet(f"{at}/msg")
        GlobalStateStore(self.spark, self.path).write(gs)
        self.spark.createDataFrame([(gs.superstep, state.schema.simpleString())], "superstep long, schema string").coalesce(1).write.mode("overwrite").parquet(f"{at}/manifest")

    def complete(self) -> list[int]:
        """Supersteps with a whole checkpoint."""
        hadoop = self.spark.sparkContext._jvm.org.apache.hadoop.fs
        root = hadoop.Path(f"{self.path}/ckpt")
        fs = root.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        if not fs.exists(root):
            return []
        found = [x.getPath() for x in fs.listStatus(root)]
        return sorted(int(p.getName()[2:]) for p in found if fs.exists(hadoop.Path(p, "manifest/_SUCCESS")))

    def restore(self) -> tuple[GlobalState, DataFrame, DataFrame] | None:
        """The newest whole checkpoint, or None."""
        steps = self.complete()
        if not steps:
            return None
        at = f"{self.path}/ckpt/s={steps[-1]:08d}"
        gs = GlobalStateStore(self.spark, self.path).read(steps[-1])
        return gs, self.spark.read.parquet(f"{at}/vertex"), self.spark.read.parquet(f"{at}/msg")
