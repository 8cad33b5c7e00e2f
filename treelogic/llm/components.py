"""Connected components of a link table, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.llm.shared import checkpointed


def _large_star(links: DataFrame) -> DataFrame:
    """Hangs each larger neighbour of a node on the node's least neighbour.

    The least is an aggregate, combined before the shuffle, and goes back by a
    join, which is dealt anew where a node has very many links.
    """
    both = links.union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min(F.least("a", "b")).alias("m"))
    return both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))


def _small_star(links: DataFrame) -> DataFrame:
    """Hangs a node and its smaller neighbours on the least of them; links are (larger, smaller)."""
    least = links.groupBy("a").agg(F.min("b").alias("m"))
    hung = links.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b")
    return hung.union(least.select("a", F.col("m").alias("b")))


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(a, root) for every node of a link table (a, b): root is the component's least node.

    Self links count as nodes of their own.  The tables shrink to stars; each
    round's table is checkpointed, and only its row count and checksum reach the
    driver.  Raises if the rounds run out.
    """
    links = checkpointed(links.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    before = None
    for _ in range(most_rounds):
        now = tuple(links.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
        if now == before or not now[0]:
            return links.select("a", F.col("b").alias("root")).union(links.select(F.col("b").alias("a"), F.col("b").alias("root"))).distinct()
        before = now
        links = checkpointed(_small_star(_large_star(links)).distinct())
    raise RuntimeError("components did not settle")
