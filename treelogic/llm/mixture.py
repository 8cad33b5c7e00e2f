"""Mixing sources to target weights by budgets on a tree.

A token budget flows down a tree of groups (domain, language, source).  At every
node the children share it by their weights; a child that cannot take its share
(its documents, repeated at most ``max_epochs`` times, hold fewer tokens) takes
what it has and its siblings share the rest by their weights again.  A node's
capacity is its children's sum, so a shortage goes up to the node's own siblings
only when all of its children are full.  All amounts are whole tokens and shares
are rounded down.

A leaf's budget is spent in epochs.  Whole epochs take every document; the last
one takes documents in the order of md5(seed:epoch:doc_id) until the budget is
used up, so its last document may be taken in part.

Scale: budgets are windows over the table of groups.  The running sum in a leaf
has two steps, over 4096 buckets of the hash and inside each bucket, so no task
holds a leaf.
"""

from __future__ import annotations

from collections.abc import Iterator, Mapping, Sequence

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from treelogic.llm import arrowkit
from treelogic.llm.shared import checkpointed

#: Groups up to which their table, which is counted, may be broadcast.
BROADCAST_GROUPS = 50_000


def with_word_counts(docs: DataFrame, into: str = "n_tokens") -> DataFrame:
    """The other columns and the number of words (runs of other than ASCII white space) of ``text``; null has none.

    The text itself is left behind: only counts travel on.
    """
    names = [c for c in docs.columns if c != "text"]
    fields = {f.name: f.dataType.simpleString() for f in docs.schema.fields}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in arrowkit.slices(batches, "text"):
            yield pa.RecordBatch.from_arrays([*[part.column(c) for c in names], pa.array(arrowkit.word_counts(part.column("text")), pa.int64())], names=[*names, into])

    return docs.mapInArrow(arrowkit.tidy(run), ", ".join([f"`{c}` {fields[c]}" for c in names] + [f"`{into}` long"]))


def weight_of(level: str, weights: Mapping[str, int], default: int = 1) -> Column:
    """A child's whole-number weight by its name."""
    out = F.lit(default).cast("long")
    for name, w in weights.items():
        out = F.when(F.col(level) == name, F.lit(w).cast("long")).otherwise(out)
    return out


def share(nodes: DataFrame, parents: Sequence[str], child: str, budget: str, into: str) -> DataFrame:
    """Shares each parent's ``budget`` among its children (columns ``weight`` and ``capacity``)."""
    by = Window.partitionBy(*parents) if parents else Window.partitionBy(F.lit(0))
    order = by.orderBy(F.col("capacity").cast("double") / F.col("weight"), child)
    before = F.coalesce(F.sum("capacity").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0).cast("long"))
    still = F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing))
    full = F.col("capacity") * still <= F.col("weight") * (F.col(budget) - before)
    nodes = nodes.withColumn("__full", full)
    left = F.col(budget) - F.coalesce(F.sum(F.when(F.col("__full"), F.col("capacity"))).over(by), F.lit(0).cast("long"))
    weight = F.sum(F.when(~F.col("__full"), F.col("weight"))).over(by)
    nodes = nodes.withColumn("__left", left).withColumn("__weight", weight)
    part = F.when(F.col("__full"), F.col("capacity")).otherwise(F.expr("weight * __left div __weight"))
    return nodes.withColumn(into, part).drop("__full", "__left", "__weight")


def budgets(leaves: DataFrame, levels: Sequence[str], weights: Mapping[str, Mapping[str, int]], total: int, max_epochs: int) -> DataFrame:
    """Adds ``leaf_budget`` to the leaves (columns ``levels`` and ``leaf_tokens``).

    Null group names stand as the empty string; weights must be positive and
    default to 1; a leaf without tokens gets nothing.
    """
    out = leaves.withColumn("__up", F.lit(total).cast("long"))
    for depth, level in enumerate(levels):
        path, parents = list(levels[:depth + 1]), list(levels[:depth])
        nodes = out.groupBy(*path, "__up").agg((F.sum("leaf_tokens") * max_epochs).alias("capacity")).withColumn("weight", weight_of(level, weights.get(level, {})))
        given = share(nodes, parents, level, "__up", "__own").select(*path, "__own")
        out = out.drop("__up").join(given, path).withColumnRenamed("__own", "__up")
    return out.withColumnRenamed("__up", "leaf_budget")


def mix_documents(docs: DataFrame, levels: Sequence[str], weights: Mapping[str, Mapping[str, int]], share_of_tokens: tuple[int, int], max_epochs: int = 1, seed: int = 0, tokens: str | None = None, keep: Sequence[str] = ()) -> DataFrame:
    """What is taken of every document: ``epochs`` (in how many it occurs) and ``taken_tokens``.

    ``levels`` name the group columns from the root down; the budget is
    ``share_of_tokens`` (numerator, denominator) of all tokens, which are words
    unless ``tokens`` names a column of whole numbers.  Returns ``doc_id``, the
    levels (null as empty), ``n_tokens``, ``epochs``, ``taken_tokens`` and
    ``keep``, one row for each input row.  Documents without tokens are in no
    epoch.  Rows with equal ids stand in the order of their tokens.
    """
    columns = ["doc_id", *[F.coalesce(F.col(c).cast("string"), F.lit("")).alias(c) for c in levels], *keep]
    if tokens:
        rows = docs.select(*columns, F.coalesce(F.col(tokens).cast("long"), F.lit(0).cast("long")).alias("n_tokens"))
    else:
        rows = with_word_counts(docs.select(*columns, "text"))
    rows = checkpointed(rows)
    leaves = checkpointed(rows.groupBy(*levels).agg(F.sum("n_tokens").alias("leaf_tokens")))
    held, groups = leaves.agg(F.sum("leaf_tokens"), F.count("*")).first()
    total = (held or 0) * share_of_tokens[0] // share_of_tokens[1]
    given = budgets(leaves, levels, weights, total, max_epochs)
    given = given.withColumn("whole", F.expr("CASE WHEN leaf_tokens > 0 THEN leaf_budget div leaf_tokens ELSE 0L END")).withColumn("rest", F.expr("leaf_budget - whole * leaf_tokens"))
    given = given.select(*levels, "whole", "rest")
    placed = rows.join(F.broadcast(given) if groups <= BROADCAST_GROUPS else given, list(levels))
    placed = placed.withColumn("__h", F.md5(F.concat_ws(":", F.lit(str(seed)), (F.col("whole") + 1).cast("string"), F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))).cast("binary")))
    placed = placed.withColumn("__b", F.substring("__h", 1, 3))
    sums = placed.groupBy(*levels, "__b").agg(F.sum("n_tokens").alias("__s"))
    ahead = sums.withColumn("__ahead", F.coalesce(F.sum("__s").over(Window.partitionBy(*levels).orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0).cast("long"))).drop("__s")
    inside = F.coalesce(F.sum("n_tokens").over(Window.partitionBy(*levels, "__b").orderBy("__h", "doc_id", "n_tokens").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0).cast("long"))
    out = placed.join(ahead, [*levels, "__b"]).withColumn("__before", F.col("__ahead") + inside)
    part = F.greatest(F.least("n_tokens", F.col("rest") - F.col("__before")), F.lit(0).cast("long"))
    out = out.withColumn("__part", part)
    epochs = F.when(F.col("n_tokens") > 0, F.col("whole") + F.when(F.col("__part") > 0, 1).otherwise(0)).otherwise(0).cast("long")
    return out.select("doc_id", *levels, "n_tokens", epochs.alias("epochs"), (F.col("whole") * F.col("n_tokens") + F.col("__part")).alias("taken_tokens"), *keep)


# Production parameters of the query and the pipeline.
LEVELS = ("domain", "lang", "source")
WEIGHTS = {"domain": {"d0": 4, "d1": 3, "d2": 2, "d3": 1}, "lang": {"en": 4, "fr": 2, "de": 2, "es": 2}}
DOMAIN_SQL = "concat('d', CAST(coalesce(try_cast(regexp_extract(source, '([0-9]+)$', 1) AS bigint), 0) % 4 AS string))"


def with_domain(docs: DataFrame) -> DataFrame:
    """Adds ``domain``: d0 to d3 by the number at the end of the source's name."""
    return docs.withColumn("domain", F.expr(DOMAIN_SQL))
