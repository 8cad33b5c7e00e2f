"""Sources and sinks: edge lists as text, pattern files, index tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treelogic.query.pattern import TreePattern


def edge_list(spark: SparkSession, path: str, separator: str = r"\s+", comment: str = "#") -> DataFrame:
    """(src, dst) from a text file with one edge a line; other lines and comments are left out."""
    parts = F.split(F.trim("value"), separator)
    rows = spark.read.text(path).filter(~F.col("value").startswith(comment)).select(parts.alias("p"))
    return rows.filter(F.size("p") >= 2).select(F.expr("try_cast(p[0] as long)").alias("src"), F.expr("try_cast(p[1] as long)").alias("dst")).filter("src is not null and dst is not null")


def json_edges(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst) from JSON lines with these fields."""
    return spark.read.schema("src long, dst long").json(path).filter("src is not null and dst is not null")


def csv_edges(spark: SparkSession, path: str, header: bool = False) -> DataFrame:
    return spark.read.schema("src long, dst long").option("header", header).csv(path).filter("src is not null and dst is not null")


def read_patterns(spark: SparkSession, path: str) -> list[TreePattern]:
    """Patterns from a file with one JSON pattern a line (pattern files are small)."""
    return [TreePattern.from_json(r[0]) for r in spark.read.text(path).collect() if r[0].strip()]


def write_patterns(spark: SparkSession, patterns: list[TreePattern], path: str) -> None:
    spark.createDataFrame([(p.to_json(),) for p in patterns], "value string").coalesce(1).write.mode("overwrite").text(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by a key, so that joins on it need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
