"""Condensation of cycles: strongly connected components by trimming and colouring."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.plans import cut


def condense(nodes: DataFrame, edges: DataFrame, most_rounds: int = 1000) -> tuple[DataFrame, DataFrame]:
    """(component, acyclic edges): ``scc(node_id, comp, cyclic)`` and ``dag(src, dst)`` between components.

    Nodes that lie on no cycle are trimmed first.  Of the rest every node takes
    the least id that reaches it; what the owner of a colour is reached by,
    inside its colour, is the owner's component.  ``comp`` is the least node of
    the component; ``cyclic`` says whether its nodes reach themselves.
    """
    edges = cut(edges.select("src", "dst").distinct())
    loops = edges.filter("src = dst").select(F.col("src").alias("node_id"))
    work = cut(edges.filter("src <> dst"))
    done: DataFrame | None = None
    for _ in range(most_rounds):
        # trim: nodes without an edge in or out lie on no cycle
        while True:
            n = work.count()
            work = cut(work.join(work.select(F.col("dst").alias("src")).distinct(), "src", "left_semi").join(work.select(F.col("src").alias("dst")).distinct(), "dst", "left_semi").select("src", "dst"))
            if work.count() == n:
                break
        if work.isEmpty():
            break
        color = cut(work.select(F.col("src").alias("node_id")).union(work.select("dst")).distinct().withColumn("color", F.col("node_id")))
        while True:
            pushed = work.join(color.withColumnRenamed("node_id", "src"), "src").select(F.col("dst").alias("node_id"), "color")
            after = cut(color.union(pushed).groupBy("node_id").agg(F.min("color").alias("color")))
            changed = after.join(color, ["node_id", "color"], "left_anti").isEmpty()
            color = after
            if changed:
                break
        same = work.join(color.select(F.col("node_id").alias("src"), "color"), "src").join(color.select(F.col("node_id").alias("dst"), F.col("color").alias("other")), "dst").filter("color = other").select("src", "dst", "color")
        same = cut(same)
        found = cut(color.filter("node_id = color"))
        while True:
            back = same.join(found.select(F.col("node_id").alias("dst"), "color"), ["dst", "color"]).select(F.col("src").alias("node_id"), "color").distinct().join(found, ["node_id", "color"], "left_anti")
            back = cut(back)
            if back.isEmpty():
                break
            found = cut(found.union(back))
        done = found if done is None else cut(done.union(found))
        gone = found.select("node_id")
        work = cut(work.join(gone.withColumnRenamed("node_id", "src"), "src", "left_anti").join(gone.withColumnRenamed("node_id", "dst"), "dst", "left_anti").select("src", "dst"))
    every = nodes.select("node_id")
    if done is None:
        scc = every.withColumn("comp", F.col("node_id")).withColumn("large", F.lit(False))
    else:
        size = done.groupBy("color").agg(F.min("node_id").alias("comp"), (F.count("*") > 1).alias("large"))
        named = done.join(size, "color").select("node_id", "comp", "large")
        scc = every.join(named, "node_id", "left").select("node_id", F.coalesce("comp", "node_id").alias("comp"), F.coalesce("large", F.lit(False)).alias("large"))
    scc = cut(scc.join(loops.withColumn("loop", F.lit(True)).distinct(), "node_id", "left").select("node_id", "comp", (F.col("large") | F.coalesce("loop", F.lit(False))).alias("cyclic")))
    a, b = scc.select(F.col("node_id").alias("src"), F.col("comp").alias("a")), scc.select(F.col("node_id").alias("dst"), F.col("comp").alias("b"))
    dag = cut(edges.join(a, "src").join(b, "dst").filter("a <> b").select(F.col("a").alias("src"), F.col("b").alias("dst")).distinct())
    return scc, dag
