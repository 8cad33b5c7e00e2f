"""Help with physical plans: cutting lineage, sizes checked before a broadcast, counting joins."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows up to which a side may be broadcast; beyond it the join shuffles.
BROADCAST_ROWS = 200_000


def shared_folder(spark: SparkSession) -> str:
    """The folder in ``spark.checkpoint.dir``; only a session without that setting (a test) gets its own."""
    folder = spark.conf.get("spark.checkpoint.dir", "") or spark.sparkContext.getCheckpointDir()
    if not folder:
        folder = tempfile.mkdtemp(prefix="checkpoint-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def cut(df: DataFrame, eager: bool = True) -> DataFrame:
    """The rows written to the shared checkpoint folder, so that plans stay short and survive lost executors."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager)


def stored(df: DataFrame) -> DataFrame:
    """The rows written to the shared folder as Parquet: more compact than ``cut``, and read by columns."""
    folder = f"{shared_folder(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.parquet(folder, compression="zstd")
    return df.sparkSession.read.schema(df.schema).parquet(folder)


def small(df: DataFrame, rows: int | None = None) -> DataFrame:
    """The table with a broadcast hint if it is counted to be small; as it is otherwise."""
    n = df.limit(BROADCAST_ROWS + 1).count() if rows is None else rows
    return F.broadcast(df) if n <= BROADCAST_ROWS else df


def apart(df: DataFrame) -> DataFrame:
    """The same rows, not shuffled, taken one by one by what follows.  Operators that are compiled together hold all that
    they make of one row until the next; between two that multiply rows, this keeps that to one's share."""
    return df.coalesce(1 << 16)


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def join_count(df: DataFrame) -> int:
    """Join operators in the physical plan."""
    return len(re.findall(r"\b(?:SortMergeJoin|BroadcastHashJoin|ShuffledHashJoin|BroadcastNestedLoopJoin|CartesianProduct)\b", plan_text(df)))
