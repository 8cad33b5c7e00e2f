"""Where intermediate tables live, and ranges of ordered rows."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder in ``spark.checkpoint.dir``; only a session without that setting (a test) gets its own."""
    folder = spark.conf.get("spark.checkpoint.dir", "") or spark.sparkContext.getCheckpointDir()
    if not folder:
        folder = tempfile.mkdtemp(prefix="checkpoint-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def checkpointed(df: DataFrame, eager: bool = True) -> DataFrame:
    """Writes the rows to the shared folder and cuts the lineage there."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager)


def parts(spark: SparkSession, at_least: int = 1) -> int:
    """The session's number of shuffle partitions."""
    return max(at_least, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def bounds(df: DataFrame, key: str, n: int) -> list[int]:
    """At most n - 1 values of an integer column that cut its rows into about equal ranges."""
    if n < 2:
        return []
    row = df.agg(F.percentile_approx(key, [i / n for i in range(1, n)], 20 * n).alias("cuts")).first()
    return sorted({int(x) for x in row["cuts"] or []})


def range_of(key: str, cuts: list[int]):
    """Number of cuts that are not above the key: 0 for keys under the first, and for nulls."""
    if not cuts:
        return F.lit(0)
    if len(cuts) > 512:  # bisection on the ids alone instead of a long literal list
        import numpy as np
        import pandas as pd

        edges = np.array(cuts, np.int64)

        @F.pandas_udf("int")
        def place(ids: pd.Series) -> pd.Series:
            return pd.Series(np.where(ids.isna(), 0, np.searchsorted(edges, ids.fillna(0).to_numpy(np.int64), side="right")).astype(np.int32))

        return place(F.col(key).cast("long"))
    table = F.array(*[F.lit(c).cast("long") for c in cuts])
    return F.coalesce(F.size(F.filter(table, lambda c: c <= F.col(key).cast("long"))), F.lit(0)).cast("int")


def shielded(df: DataFrame, *needed: str) -> tuple[DataFrame, list]:
    """The rows with all but the needed columns under names that clash with nothing, and the
    columns that give back the original names."""
    names = {c: c if c in needed else f"__kept{i}" for i, c in enumerate(df.columns)}
    return df.select(*[F.col(f"`{c}`").alias(n) for c, n in names.items()]), [F.col(n).alias(c) for c, n in names.items()]


def drop_folder(spark: SparkSession, folder: str) -> None:
    """Deletes a folder by the file system that its path names; a missing one is no error."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
