"""Exact top-k search by inner product, with MaxScore.

Terms are the dimensions, a vector's weight on a term its whole-number
component.  Candidates lie in blocks that know the least and the greatest
component of every term, which bounds what each term can add to a query's score
there.  With the score of the k-th best found so far as the bar, the terms of
least bound that together stay under the bar are non-essential: a vector that
has nothing but them cannot enter the list.  The essential terms' postings are
traversed first (for all vectors of a block at once, as a product of matrices in
which the other weights are zero); the non-essential terms are probed only for
vectors that can still reach the bar.  A block whose bounds sum up to less than
the bar is passed over.

Scale: query blocks and candidate blocks meet in the cells of a grid by an
equi-join on the cell's number; each cell sends its k best for each query and
these are merged.  A cell holds a bounded number of queries and one candidate
block at a time.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treelogic.llm import arrowkit
from treelogic.llm.shared import parts

BLOCK_ROWS = 4096
QUERIES_A_CELL = 8192
CANDIDATES_A_CELL = 16384
#: Share of a block's vectors above which probing one by one costs more than a second product.
DENSE = 0.05
#: Share of the bar up to which the bounds of the non-essential terms may sum.
REST_SHARE = 0.35


def whole_numbers(batch: pa.RecordBatch, scale: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids, floor(scale * x)) of the rows; shorter vectors are filled up with zeros."""
    column = batch.column("embedding")
    offsets = column.offsets.to_numpy()
    values = np.floor(column.values.to_numpy(zero_copy_only=False).astype(np.float64) * scale)
    size = np.diff(offsets)
    width = int(size.max(initial=0))
    if len(size) and (size == width).all():
        matrix = values[offsets[0]:offsets[-1]].reshape(len(size), width)
    else:
        matrix = np.zeros((len(size), width))
        for i, (a, b) in enumerate(zip(offsets[:-1], offsets[1:])):
            matrix[i, :b - a] = values[a:b]
    return batch.column("vec_id").to_numpy(), matrix


def _pack(scale: int, rows: int):
    """Blocks of (ids, matrix), rows by ascending id."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        n = 0

        def close() -> pa.RecordBatch:
            ids, x = whole_numbers(pa.Table.from_batches(held).combine_chunks().to_batches()[0], scale)
            order = np.argsort(ids, kind="stable")
            return pa.RecordBatch.from_arrays([pa.array([ids[order].tobytes()], pa.binary()), pa.array([x[order].tobytes()], pa.binary()), pa.array([x.shape[1]], pa.int32())], names=["ids", "matrix", "width"])

        for batch in batches:
            at = 0
            while at < batch.num_rows:
                part = batch.slice(at, rows - n)
                held.append(part)
                n += part.num_rows
                at += part.num_rows
                if n == rows:
                    yield close()
                    held, n = [], 0
        if n:
            yield close()

    return run


class MaxScore:
    """k best of the blocks fed so far for a set of queries."""

    def __init__(self, ids: np.ndarray, weights: np.ndarray, k: int):
        self.ids, self.weights, self.k = ids, weights, k
        self.best: list[tuple[np.ndarray, np.ndarray]] = [(np.zeros(0, np.int64), np.zeros(0)) for _ in ids]
        self.bar = np.full(len(ids), -np.inf)
        self.probed = self.passed = 0

    def feed(self, ids: np.ndarray, x: np.ndarray) -> None:
        width = max(self.weights.shape[1], x.shape[1])
        x = np.pad(x, ((0, 0), (0, width - x.shape[1])))
        q = np.pad(self.weights, ((0, 0), (0, width - self.weights.shape[1])))
        bound = np.maximum(q * x.max(axis=0), q * x.min(axis=0))
        order = np.argsort(bound, axis=1)
        # non-essential: the longest run of least bounds whose sum stays below the bar, all others being essential
        summed = np.cumsum(np.take_along_axis(bound, order, axis=1), axis=1)
        for at in range(0, len(q), 256):
            rows = np.arange(at, min(at + 256, len(q)))
            rows = rows[summed[rows, -1] >= self.bar[rows]]
            self.passed += min(256, len(q) - at) - len(rows)
            if len(rows):
                self._block(rows, q, x, ids, order, summed)

    def _block(self, rows, q, x, ids, order, summed) -> None:
        k, bar = self.k, self.bar[rows]
        # terms that add up to less than the bar are non-essential; a share of it keeps the probes few
        room = np.where(bar > 0, REST_SHARE * np.where(np.isinf(bar), 0, bar), -np.inf)
        count = (np.maximum.accumulate(summed[rows], axis=1) <= room[:, None]).sum(axis=1)
        rest_bound = np.where(count > 0, summed[rows, np.maximum(count - 1, 0)], 0)
        light = np.arange(q.shape[1])[None, :] < count[:, None]
        mask = np.zeros_like(light)
        np.put_along_axis(mask, order[rows], light, axis=1)
        essential = np.where(mask, 0, q[rows])
        rest = np.where(mask, q[rows], 0)
        score = essential @ x.T
        alive = score + rest_bound[:, None] >= bar[:, None]
        if count.any():
            if alive.mean() > DENSE:
                score += rest @ x.T
            else:
                i, j = np.nonzero(alive)
                self.probed += len(i)
                score[i, j] += np.einsum("ij,ij->i", rest[i], x[j])
        score[~alive] = -np.inf
        score[ids[None, :] == self.ids[rows][:, None]] = -np.inf
        level = np.partition(score, -k, axis=1)[:, -k] if score.shape[1] > k else np.full(len(rows), -np.inf)
        i, j = np.nonzero((score >= np.maximum(level, bar)[:, None]) & (score > -np.inf))
        edges = np.searchsorted(i, np.arange(len(rows) + 1))
        for r in np.flatnonzero(np.diff(edges)):
            at = j[edges[r]:edges[r + 1]]
            old_ids, old = self.best[rows[r]]
            all_ids, all_scores = np.concatenate((old_ids, ids[at])), np.concatenate((old, score[r, at]))
            top = np.lexsort((all_ids, -all_scores))[:k]
            self.best[rows[r]] = all_ids[top], all_scores[top]
            if len(top) == k:
                self.bar[rows[r]] = all_scores[top[-1]]


def _search(k: int):
    """Rows sorted by cell, queries before candidates."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, held, search = None, [], None

        def close():
            if search is None:
                return
            number = [len(b[0]) for b in search.best]
            if sum(number):
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(search.ids, number)), pa.array(np.concatenate([b[0] for b in search.best])), pa.array(np.concatenate([b[1] for b in search.best]).astype(np.int64))], names=["query_id", "vec_id", "score"])

        for batch in batches:
            for c, kind, ids, matrix, width in zip(*(batch.column(x) for x in ("cell", "kind", "ids", "matrix", "width"))):
                if c.as_py() != cell:
                    yield from close()
                    cell, held, search = c.as_py(), [], None
                i = np.frombuffer(ids.as_buffer(), np.int64)
                x = np.frombuffer(matrix.as_buffer(), np.float64).reshape(len(i), width.as_py())
                if kind.as_py() == 0:
                    held.append((i, x))
                elif held:
                    if search is None:
                        wide = max(x.shape[1] for _, x in held)
                        search = MaxScore(np.concatenate([i for i, _ in held]), np.concatenate([np.pad(x, ((0, 0), (0, wide - x.shape[1]))) for _, x in held]), k)
                    search.feed(i, x)
        yield from close()

    return run


def top_k(queries: DataFrame, candidates: DataFrame, k: int = 20, scale: int = 64) -> DataFrame:
    """The k highest inner products of every query with the candidates that are not the query's own row.

    Both tables have ``vec_id`` and ``embedding``.  Components become
    floor(scale * x), so scores are whole numbers and exact (below 2**53).  Ties
    go to the smaller vec_id.  Rows with a null id, or a vector that is null or
    holds null or non-finite components, take no part; shorter vectors count as
    filled up with zeros.  Queries should have distinct ids (rows that repeat one
    compete for the same k places).  Returns query_id, rank (from 1), vec_id, score.
    """
    def clean(df: DataFrame) -> DataFrame:
        x = F.col("embedding")
        good = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
        return df.select(F.col("vec_id").cast("long").alias("vec_id"), x.cast("array<double>").alias("embedding")).filter(F.col("vec_id").isNotNull() & x.isNotNull() & good)

    queries, candidates = clean(queries), clean(candidates)
    n_queries, n = queries.count(), candidates.count()
    wide = max(1, -(-n_queries // QUERIES_A_CELL))
    high = max(1, -(-n // CANDIDATES_A_CELL))
    schema = "ids binary, matrix binary, width int"
    number = F.monotonically_increasing_id()
    q = queries.mapInArrow(arrowkit.tidy(_pack(scale, 512)), schema).withColumn("own", F.pmod(F.hash(number), F.lit(wide)))
    q = q.withColumn("cell", F.explode(F.sequence(F.lit(0), F.lit(high - 1)))).withColumn("cell", F.col("own") * high + F.col("cell"))
    c = candidates.mapInArrow(arrowkit.tidy(_pack(scale, BLOCK_ROWS)), schema).withColumn("own", F.pmod(F.hash(number), F.lit(high)))
    c = c.withColumn("cell", F.explode(F.sequence(F.lit(0), F.lit(wide - 1)))).withColumn("cell", F.col("cell") * high + F.col("own"))
    columns = ["cell", "kind", "ids", "matrix", "width"]
    cells = q.withColumn("kind", F.lit(0)).select(columns).union(c.withColumn("kind", F.lit(1)).select(columns))
    found = cells.repartition(min(wide * high, 4 * parts(queries.sparkSession)), "cell").sortWithinPartitions("cell", "kind").mapInArrow(arrowkit.tidy(_search(k)), "query_id long, vec_id long, score long")
    place = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", place).filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
