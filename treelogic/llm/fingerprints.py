"""Threshold-scaled sketches of documents, and how alike two of them are.

A sketch keeps every distinct shingle hash below a fixed fraction of the hash
range.  Whether a hash is kept depends on the hash alone, so the sketch of a
union is the union of sketches, and for two documents of whatever sizes the
kept hashes that they share estimate how much of the smaller lies in the larger.
The fraction is one for all documents, long or short; sketches of different
fractions are merged and compared below the smaller one, so both stay exact set
operations.  A document with few shingles has few hashes or none: its estimates
are as coarse as that.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.llm import arrowkit
from treelogic.llm.arrowkit import U64, mix
from treelogic.llm.shared import bounds, parts, range_of

SHINGLE_WORDS = 5
#: One hash of this many is kept.
SCALE = 4


class Sketch:
    """Sorted kept hashes and the scale below which they are complete."""

    __slots__ = ("hashes", "scale")

    def __init__(self, hashes: np.ndarray, scale: int):
        self.hashes, self.scale = hashes, scale

    @classmethod
    def of(cls, shingles: np.ndarray, scale: int = SCALE) -> Sketch:
        """Of a set of shingle hashes."""
        hashes = mix(shingles, 80)
        return cls(np.sort(hashes[hashes < _edge(scale)]), scale)

    def below(self, scale: int) -> np.ndarray:
        return self.hashes if scale <= self.scale else self.hashes[:int(np.searchsorted(self.hashes, _edge(scale)))]

    def merge(self, other: Sketch) -> Sketch:
        """The sketch of the two shingle sets' union: equal to the one made of the union itself."""
        scale = max(self.scale, other.scale)
        return Sketch(np.union1d(self.below(scale), other.below(scale)), scale)

    def _overlap(self, other: Sketch) -> tuple[int, int, int]:
        scale = max(self.scale, other.scale)
        a, b = self.below(scale), other.below(scale)
        return len(np.intersect1d(a, b, assume_unique=True)), len(a), len(b)

    def containment(self, other: Sketch) -> float:
        """Estimated share of the smaller set that lies in the other: 1 for two empty sets."""
        if self.scale == other.scale and np.array_equal(self.hashes, other.hashes):
            return 1.0
        common, a, b = self._overlap(other)
        return common / min(a, b) if a and b else 0.0

    def jaccard(self, other: Sketch) -> float:
        """Estimated Jaccard similarity: 1 for two empty sets."""
        common, a, b = self._overlap(other)
        return common / (a + b - common) if a or b else 1.0

    def text(self) -> str:
        """The scale, a colon and the hashes as 16 hexadecimal digits each."""
        return f"{self.scale}:{self.hashes.astype('>u8').tobytes().hex()}"

    @classmethod
    def parse(cls, text: str) -> Sketch:
        scale, _, digits = text.partition(":")
        return cls(np.frombuffer(bytes.fromhex(digits), ">u8").astype(U64), int(scale))


def _edge(scale: int) -> np.uint64:
    """The end of the fraction 1 / scale of the hash range."""
    return U64((2**64 - 1) // scale)


def sketches(texts: pa.Array, k: int = SHINGLE_WORDS, scale: int = SCALE) -> list[Sketch]:
    return [Sketch.of(s, scale) for s in arrowkit.Words(texts).shingle_sets(k)]


def fingerprint_documents(docs: DataFrame, k: int = SHINGLE_WORDS, scale: int = SCALE, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` and the ``fingerprint`` of every whole text (null: empty).  Narrow: no shuffle."""
    names = [*keep]
    source = docs.select(*names, F.col(text).alias("__text"))
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema if f.name in names] + ["fingerprint string"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in arrowkit.slices(batches, "__text", 2 << 20):
            prints = [s.text() for s in sketches(part.column("__text"), k, scale)]
            yield pa.RecordBatch.from_arrays([*[part.column(c) for c in names], pa.array(prints, pa.string())], names=[*names, "fingerprint"])

    return source.mapInArrow(arrowkit.tidy(run), schema)


def _compare(k: int, scale: int):
    """Rows of ranges (part, ahead, doc_id, text), sorted; ``ahead`` marks the first rows of the next range."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []  # the last row, whose successor has not come yet

        def done(rows: list[tuple], after: list[str]) -> pa.RecordBatch:
            edited = []
            for (_, _, _, t), nxt in zip(rows, after):
                half = len(t) // 2
                edited.append(t[:len(t) - half] + nxt[:half])
            n = len(rows)
            prints = sketches(pa.array([r[3] for r in rows] + edited + after, pa.string()), k, scale)
            own, changed, following = prints[:n], prints[n:2 * n], prints[2 * n:]
            return pa.RecordBatch.from_arrays([
                pa.array([r[2] for r in rows], pa.int64()), pa.array([len(r[3]) for r in rows], pa.int64()), pa.array([hashlib.sha256(e.encode()).hexdigest() for e in edited], pa.string()),
                pa.array([s.text() for s in own], pa.string()), pa.array([s.text() for s in changed], pa.string()),
                pa.array([a.containment(b) for a, b in zip(own, changed)], pa.float64()), pa.array([a.containment(b) for a, b in zip(own, following)], pa.float64()),
            ], names=["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

        rows: list[tuple] = []
        after: list[str] = []
        size = 0
        for part in arrowkit.slices(batches, "text", 1 << 20):
            for row in zip(*(part.column(c).to_pylist() for c in ("part", "ahead", "doc_id", "text"))):
                if held and held[0][0] == row[0] and not held[0][1]:
                    rows.append(held[0])
                    after.append(row[3])
                    size += len(held[0][3]) + len(row[3])
                held = [row]
                if size > 1 << 20:
                    yield done(rows, after)
                    rows, after, size = [], [], 0
        if rows:
            yield done(rows, after)

    return run


def compare_with_edits(docs: DataFrame, k: int = SHINGLE_WORDS, scale: int = SCALE) -> DataFrame:
    """Fingerprints of every text and of its edited text, and their likeness.

    The edited text ends in the beginning of the next document (ascending
    doc_id, equal ids by text, nulls first; after the last comes the first).
    Documents are dealt in ranges of doc_id by one shuffle; a range's first
    document also goes to the range before it, so that no range needs another.
    A null text is empty; a table with a single row is its own next document.
    """
    spark = docs.sparkSession
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    ends = source.agg(F.min("doc_id"), F.count(F.when(F.col("doc_id").isNull(), 1))).first()
    n = parts(spark)
    cuts = [c for c in bounds(source, "doc_id", 2 * n) if ends[0] is not None and c > ends[0]]
    part = range_of("doc_id", cuts)
    lowest = F.col("doc_id").isNull() if ends[1] else F.col("doc_id") == F.lit(ends[0])
    first_of_range = F.lit(False) if not cuts else F.col("doc_id").isin(cuts)
    before = F.when(lowest, F.lit(len(cuts))).when(first_of_range, part - 1)
    places = F.array(F.struct(part.alias("part"), F.lit(False).alias("ahead")), F.struct(before.alias("part"), F.lit(True).alias("ahead")))
    dealt = source.withColumn("place", F.explode(F.filter(places, lambda x: x["part"].isNotNull()))).select("place.part", "place.ahead", "doc_id", "text")
    ordered = dealt.repartition(n, "part").sortWithinPartitions("part", "ahead", "doc_id", "text")
    return ordered.mapInArrow(arrowkit.tidy(_compare(k, scale)), "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
