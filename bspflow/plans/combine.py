"""Message combination: a user's combiner under each group-by and connector."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .hints import Connector, GroupBy


@dataclass(frozen=True)
class Combiner:
    """``final`` folds the payloads of a destination; ``arrow`` names an Arrow aggregate that pre-folds them, if any."""

    name: str
    final: Callable[[Column], Column]
    arrow: str | None = None


MIN = Combiner("min", F.min, "min")
MAX = Combiner("max", F.max, "max")
SUM = Combiner("sum", F.sum, "sum")
#: smallest struct: ties of the first field go to the next
STRUCT_MIN = Combiner("struct_min", F.min)
#: all payloads, in sorted order so that reruns agree
LIST = Combiner("list", lambda c: F.array_sort(F.collect_list(c)))
COUNT = Combiner("count", lambda c: F.sum(c), "sum")


def _prefold(kind: str):
    """Fold equal destinations inside each Arrow batch at the sender."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                folded = pa.Table.from_batches([batch]).group_by("vid").aggregate([("payload", kind)])
                out = folded.select(["vid", f"payload_{kind}"]).rename_columns(["vid", "payload"]).cast(batch.schema)
                yield from out.to_batches()

    return run


def combine(raw: DataFrame, combiner: Combiner, groupby: GroupBy, connector: Connector, partitions: int) -> DataFrame:
    """``raw``(vid, payload) -> one row a vid, partitioned by vid.

    PLAIN: partial aggregation, one exchange, final aggregation; SORT sorts each sender's rows first.  MERGE: the
    sender folds what it has in a batch, rows are dealt and sorted by vid, and the receiver groups in one pass.
    Spark's shuffle has no merging reader, so MERGE sorts at the receiver instead of merging sorted runs.
    """
    if connector is Connector.PLAIN:
        rows = raw.sortWithinPartitions("vid") if groupby is GroupBy.SORT else raw
        return rows.groupBy("vid").agg(combiner.final(F.col("payload")).alias("payload"))
    rows = raw.sortWithinPartitions("vid") if groupby is GroupBy.SORT else raw
    if combiner.arrow:
        rows = rows.mapInArrow(_prefold(combiner.arrow), raw.schema)
    dealt = rows.repartition(partitions, "vid").sortWithinPartitions("vid")
    return dealt.groupBy("vid").agg(combiner.final(F.col("payload")).alias("payload"))


def settings(groupby: GroupBy, connector: Connector) -> dict[str, str]:
    """Session settings under which the plan of ``combine`` is made: sorted input is grouped by sort."""
    sort = groupby is GroupBy.SORT or connector is Connector.MERGE
    return {"spark.sql.execution.replaceHashWithSortAgg": str(sort).lower()}
