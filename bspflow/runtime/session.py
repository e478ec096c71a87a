"""Scoped session settings, the shared folder, and tables pinned across supersteps."""

from __future__ import annotations

import tempfile
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


@contextmanager
def settings(spark: SparkSession, **values: str):
    """Set session settings for a block and restore them."""
    return_to = {k: spark.conf.get(k, None) for k in values}
    try:
        for k, v in values.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in return_to.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def scoped(spark: SparkSession, values: dict[str, str]):
    return settings(spark, **values)


def fresh_session(spark: SparkSession) -> SparkSession:
    """Another session of the same cluster with this one's settings, which it may then change for itself."""
    own = spark.newSession()
    for k, v in spark.conf.getAll.items():
        if k.startswith("spark.sql.") and own.conf.isModifiable(k):
            own.conf.set(k, v)
    return own


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` where the cluster names one; on one machine, a folder of this session where it does not."""
    said = spark.conf.get("spark.checkpoint.dir", None)
    sc = spark.sparkContext
    there = sc._jsc.sc().getCheckpointDir()
    if not there.isDefined():
        if not said and sc.master.split("[")[0] != "local":
            raise RuntimeError("spark.checkpoint.dir is unset: executors need a folder that all of them see")
        sc.setCheckpointDir(said or tempfile.mkdtemp(prefix="bspflow-"))
        there = sc._jsc.sc().getCheckpointDir()
    return (said or there.get()).rstrip("/")


def choose_partitions(spark: SparkSession, n_bytes: int | None = None, per_partition: int = 256 << 20) -> int:
    """Partitions of a job: the session's shuffle partitions, or more if the state's bytes ask for it."""
    base = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return max(base, -(-n_bytes // per_partition)) if n_bytes else base


def row_partitions(spark: SparkSession, n_rows: int, per_partition: int = 1 << 17) -> int:
    """Partitions of a job over few rows: as many as give each task work that outweighs its start and its file, at most the session's."""
    return max(1, min(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-n_rows // per_partition)))


class Pins:
    """Tables that the next supersteps read, checkpointed into the shared folder.

    A checkpoint ends both the lineage and the logical plan (a persisted table would carry the plans of all steps
    before it), keeps partitioning and order while adaptive execution is off, and outlives lost executors.  Files of
    past steps are deleted as soon as nothing reads them.
    """

    def __init__(self, spark: SparkSession):
        self.spark, self.age, self.held = spark, 0, []
        shared_folder(spark)

    def pin(self, df: DataFrame, age: int | None = None) -> DataFrame:
        kept = df.checkpoint(eager=True)
        self.held.append((self.age if age is None else age, kept))
        return kept

    def drop_before(self, age: int, keep: tuple = ()) -> None:
        """Delete the files of tables pinned before ``age``, but those of ``keep``."""
        kept = []
        for a, df in self.held:
            if a < age and not any(df is k for k in keep):
                discard(df)
            else:
                kept.append((a, df))
        self.held = kept

    def close(self) -> None:
        self.drop_before(1 << 60)


def discard(df: DataFrame) -> None:
    """Delete the checkpoint files of a checkpointed table."""
    spark = df.sparkSession
    there = df._jdf.queryExecution().logical().rdd().getCheckpointFile()
    if there.isDefined():
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(there.get())
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
