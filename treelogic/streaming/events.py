"""Structured Streaming over the activity graph.

The pattern methods are defined on whole graphs; a stream grows one.  Parent-
child patterns over the next event of a user need the user's last event only,
which is keyed state with a timeout; counts are windowed with a watermark, so
late events are dropped and state stays bounded.  Negation (no such next event)
can be told only when the watermark has passed.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from treelogic.plans import shared_folder

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
PAIR_SCHEMA = "user_id long, src long, dst long, src_type string, dst_type string, closed boolean"


def read_events(spark: SparkSession, folder: str, files: str = "*.parquet", files_a_trigger: int | None = None) -> DataFrame:
    """A stream of the event files in a folder."""
    reader = spark.readStream.schema(SCHEMA).option("pathGlobFilter", files)
    if files_a_trigger:
        reader = reader.option("maxFilesPerTrigger", files_a_trigger)
    return reader.parquet(folder)


def label_counts(events: DataFrame, width: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Events of each type in tumbling (or sliding) windows."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(window, "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), "event_type", "n")


def session_counts(events: DataFrame, gap: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Sessions of users: a new one after a gap."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def next_pairs(events: DataFrame, late: str = "1 hour", wait: str = "365 days") -> DataFrame:
    """(src, dst) of each user's consecutive events, from one row of state for each user.

    A user without an event for ``wait`` gets a closing row (dst null, closed):
    what has no next event can be told from then on.
    """
    hours = pd.Timedelta(wait) / pd.Timedelta("1ms")

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        names = [c.split()[0] for c in PAIR_SCHEMA.split(", ")]
        if state.hasTimedOut:
            last, kind = state.get
            state.remove()
            yield pd.DataFrame([(key[0], last, None, kind, None, True)], columns=names)
            return
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        last, kind = state.get if state.exists else (None, None)
        out = []
        for event, label in zip(rows["event_id"], rows["event_type"]):
            if last is not None:
                out.append((key[0], last, event, kind, label, False))
            last, kind = event, label
        state.update((int(last), str(kind)))
        state.setTimeoutTimestamp(int(max(state.getCurrentWatermarkMs(), int(rows["ts"].max().timestamp() * 1000)) + hours))
        yield pd.DataFrame(out, columns=names).astype({"user_id": "int64", "src": "Int64", "dst": "Int64"})

    return events.withWatermark("ts", late).groupBy("user_id").applyInPandasWithState(step, PAIR_SCHEMA, "last long, kind string", "append", GroupStateTimeout.EventTimeTimeout)


def pc_pairs(first: DataFrame, second: DataFrame, within: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: an event of the first stream and one of the second of the same user after it."""
    a = first.select(F.col("user_id").alias("user_a"), F.col("ts").alias("ts_a"), F.col("event_id").alias("src")).withWatermark("ts_a", late)
    b = second.select(F.col("user_id").alias("user_b"), F.col("ts").alias("ts_b"), F.col("event_id").alias("dst")).withWatermark("ts_b", late)
    return a.join(b, F.expr(f"user_a = user_b and ts_b > ts_a and ts_b <= ts_a + interval {within}")).select("src", "dst")


def run_once(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over what is there (available now) into a table in the shared folder and returns it.

    In complete mode every batch holds the whole result and the last one counts;
    in append mode the batches add up.  Nothing but the batches' numbers reaches
    the driver; the query's checkpoint lies beside the table.
    """
    spark = stream.sparkSession
    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"

    def sink(batch: DataFrame, number: int) -> None:
        # a batch that is run again overwrites what it wrote before
        batch.write.mode("overwrite").parquet(f"{folder}/{'all' if mode == 'complete' else f'batch={number}'}")

    stream.writeStream.foreachBatch(sink).outputMode(mode).option("checkpointLocation", f"{folder}-state").trigger(availableNow=True).start().awaitTermination()
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    if not path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(path):
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(f"{folder}/all" if mode == "complete" else folder).select(*stream.columns)
