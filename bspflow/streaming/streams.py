"""Events as a stream of edges: windows, deduplication, static joins, running state, and incremental components.

Each query replays the table with the available-now trigger and equals its batch form.
"""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..algos.structure import min_label
from ..graphs import PAIR_SQL, PAIRS, table
from ..runtime.session import shared_folder


def source(spark: SparkSession, sf_dir: str, name: str = "events") -> DataFrame:
    """A table's file, or its folder of part files, as a stream; times become timestamps for the watermark."""
    schema = table(spark, sf_dir, name).schema
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs
    at = hadoop.Path(f"{sf_dir}/{name}.parquet")
    folder = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(at).isDirectory()
    reader = spark.readStream.schema(schema)
    rows = reader.parquet(f"{sf_dir}/{name}.parquet") if folder else reader.option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in schema.names else rows


def replay(stream: DataFrame, mode: str, batch=None) -> DataFrame:
    """Run a stream over what is there and return what it gave, as files of the shared folder: nothing passes the driver."""
    spark, made = stream.sparkSession, []
    root = f"{shared_folder(spark)}/stream-s_{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{root}/log")

    def whole(rows: DataFrame, n: int) -> None:
        rows.write.mode("overwrite").parquet(f"{root}/out/{n}")
        made.append(n)

    if batch or mode == "complete":  # files can't be the sink of a mode that gives all rows again each time
        writer.foreachBatch(batch or whole).start().awaitTermination()
    else:
        writer.format("parquet").option("path", f"{root}/out").start().awaitTermination()
    if batch:
        return None
    if mode == "complete" and not made:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(f"{root}/out/{made[-1]}" if mode == "complete" else f"{root}/out")


def _micros(c: str):
    return F.unix_micros(F.col(c)).alias("start_us")


def s_tumbling(spark, d):
    rows = source(spark, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour"), "event_type").count()
    return replay(rows, "complete").select(_micros("window.start"), "event_type", F.col("count").alias("n"))


def s_sliding(spark, d):
    rows = source(spark, d).groupBy(F.window("ts", "1 hour", "15 minutes"), "event_type").count()
    return replay(rows, "complete").select(_micros("window.start"), "event_type", F.col("count").alias("n"))


def s_session(spark, d):
    rows = source(spark, d).groupBy(F.session_window("ts", "30 minutes"), "user_id").count()
    return replay(rows, "complete").select(_micros("session_window.start"), "user_id", F.col("count").alias("n"))


def s_dedup(spark, d):
    twice = source(spark, d).withColumn("x", F.explode(F.array(F.lit(1), F.lit(2)))).drop("x")
    rows = twice.withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["event_id"])
    return replay(rows.select("event_id", "user_id"), "append")


def s_stream_static(spark, d):
    static = table(spark, d, "events").groupBy("user_id").agg(F.count("*").alias("degree"))
    rows = source(spark, d).where("event_type = 'error'").join(static, "user_id").select("event_id", "user_id", "degree")
    return replay(rows, "append")


def o_join_interval_stream(spark, d):
    """Two streams joined within an hour: watermarks and the bound on time let both sides forget."""
    both = source(spark, d).select("event_id", "user_id", "event_type", "ts")
    bought = both.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("buyer"), F.col("ts").alias("at")).withWatermark("at", "1 hour")
    seen = both.select(F.col("event_id").alias("event"), "user_id", "ts").withWatermark("ts", "1 hour")
    rows = bought.join(seen, F.expr("buyer = user_id AND ts > at AND ts <= at + INTERVAL 1 HOUR"))
    return replay(rows.select("purchase", "event"), "append")


def s_late(spark, d):
    """Events that come too late, by kind: odd ids arrive first, even ones after, and the watermark is an hour.

    The stream keeps what is in time; late rows are those that it has dropped.
    """
    root = f"{shared_folder(spark)}/late-{uuid.uuid4().hex}"
    events = table(spark, d, "events").select("event_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    for turn in (1, 0):  # two runs of one query: the second goes on with the first one's watermark
        events.where(F.col("event_id") % 2 == turn).write.mode("append").parquet(f"{root}/in")
        stream = spark.readStream.schema(events.schema).parquet(f"{root}/in").withWatermark("ts", "1 hour")
        writer = stream.dropDuplicates(["event_id", "ts"]).writeStream.outputMode("append").trigger(availableNow=True).format("parquet").option("path", f"{root}/kept")
        writer.option("checkpointLocation", f"{root}/log").start().awaitTermination()
    kept = spark.read.schema(events.schema).parquet(f"{root}/kept")
    return events.join(kept, "event_id", "left_anti").groupBy("event_type").agg(F.count("*").alias("n"))


def s_stateful_degree(spark, d):
    """Running number of events of each user, kept as state: a row a user and micro-batch."""

    def count(key, batches, state):
        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [n]})

    rows = source(spark, d).select(F.col("user_id").cast("long").alias("user_id"))
    kept = rows.groupBy("user_id").applyInPandasWithState(count, "user_id long, degree long", "n long", "append", GroupStateTimeout.NoTimeout)
    return replay(kept, "append").groupBy("user_id").agg(F.max("degree").alias("degree"))


def s_incremental_cc(spark, d):
    """Micro-batches of new links merge the labels kept so far: a batch links labels, and labels follow."""
    root, made = f"{shared_folder(spark)}/cc-{uuid.uuid4().hex}", {"n": 0}
    path = f"{root}/edges"
    PAIRS["order"](spark, d).repartition(3).write.parquet(path)

    def merge(batch: DataFrame, _: int) -> None:
        links = batch.select("src", "dst")
        ends = links.select(F.col("src").alias("vid")).union(links.select("dst")).distinct()
        if made["n"]:
            old = batch.sparkSession.read.parquet(f"{root}/labels/{made['n']}")
            ends = ends.union(old.select("vid")).distinct()
            links = links.union(old.where("vid <> label").select(F.col("vid").alias("src"), F.col("label").alias("dst")))
        min_label(links, ends).write.parquet(f"{root}/labels/{made['n'] + 1}")
        made["n"] += 1

    stream = spark.readStream.schema("src long, dst long, weight long").option("maxFilesPerTrigger", 1).parquet(path)
    replay(stream, "append", merge)
    return spark.read.parquet(f"{root}/labels/{made['n']}").select("vid", "label")


QUERIES = {f.__name__: f for f in (s_tumbling, s_sliding, s_session, s_dedup, s_late, s_stream_static, s_stateful_degree, o_join_interval_stream, s_incremental_cc)}
SQL = {
    "s_tumbling": "SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start_us, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2",
    "s_sliding": """SELECT epoch_us(time_bucket(INTERVAL 15 MINUTE, ts)) - k * 900000000 AS start_us, event_type, count(*)::BIGINT AS n
 FROM events, (SELECT unnest(range(0, 4)) AS k) GROUP BY 1, 2""",
    "s_session": """WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events),
 k AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM g) SELECT epoch_us(min(ts)) AS start_us, user_id, count(*)::BIGINT AS n FROM k GROUP BY user_id, s""",
    "s_dedup": "SELECT event_id, user_id FROM events",
    "s_late": """SELECT event_type, count(*)::BIGINT AS n FROM events WHERE event_id % 2 = 0
 AND ts <= (SELECT date_trunc('millisecond', max(ts)) - INTERVAL 1 HOUR FROM events WHERE event_id % 2 = 1) GROUP BY 1""",
    "s_stateful_degree": "SELECT user_id::BIGINT AS user_id, count(*)::BIGINT AS degree FROM events GROUP BY 1",
    "o_join_interval_stream": """SELECT p.event_id AS purchase, e.event_id AS event FROM events p JOIN events e ON p.user_id = e.user_id
 AND p.event_type = 'purchase' AND e.ts > p.ts AND e.ts <= p.ts + INTERVAL 1 HOUR""",
    "s_stream_static": "SELECT event_id, user_id, degree FROM events JOIN (SELECT user_id, count(*)::BIGINT AS degree FROM events GROUP BY 1) USING (user_id) WHERE event_type = 'error'",
    "s_incremental_cc": f"""WITH RECURSIVE p AS ({PAIR_SQL['order']}), e AS MATERIALIZED (SELECT src, dst FROM p UNION SELECT dst, src FROM p),
 t(vid, label) USING KEY (vid) AS (SELECT src, src FROM e GROUP BY 1 UNION SELECT x.vid, x.label FROM (SELECT e.dst AS vid, min(t.label) AS label FROM t JOIN e ON e.src = t.vid GROUP BY e.dst) x
 JOIN recurring.t r ON r.vid = x.vid WHERE x.label < r.label) SELECT vid, label FROM t""",
}
