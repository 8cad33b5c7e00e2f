"""Repeated passages: winnowed seeds, extended both ways, kept from a length on.

A repeat is a run of at least ``min_words`` words that also starts elsewhere.
Every window of ``min_words`` words selects one of its ``seed_words``-word runs,
the one of least hash (the rightmost of equals), by its content alone.  So two
equal windows have the same seed at the same place, and documents need to meet
on their seeds only.  A seed carries what lies left and right of it as the
hashes of the windows that selected it, one for each possible reach to the left
and the right; where two occurrences of a seed agree in such a hash they extend
to a whole window.  Overlapping windows of a document are merged: the maximal
repeats.

Scale: a chunk of texts sends one packed row to each bucket of seeds.  A window
that a chunk holds several times is settled there and sent once, so a passage
that a third of all documents share costs a chunk one entry, not one for each
document, and no pairs of documents are made.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.llm import arrowkit
from treelogic.llm.arrowkit import U64, mix, ranges
from treelogic.llm.shared import parts

#: Low bits of a seed's rank that hold its place, so that ties go to the right.
_PLACE = U64((1 << 28) - 1)
_LOW48 = U64((1 << 48) - 1)
CHUNK_BYTES = 4 << 20
#: Buckets of seeds for each shuffle partition: a task holds one bucket at a time.
BUCKETS_A_TASK = 8


def sliding_least(values: np.ndarray, width: int) -> np.ndarray:
    """Least value of each run of ``width`` values, by doubling."""
    n = len(values) - width + 1
    if n <= 0:
        return values[:0]
    have, out = 1, values
    while have * 2 <= width:
        out = np.minimum(out[:-have], out[have:])
        have *= 2
    rest = width - have
    return np.minimum(out[:n], out[rest:rest + n])


def seeds(words: arrowkit.Words, min_words: int, seed_words: int):
    """For each window: its first word, its hash, its seed's hash and place; windows in text order."""
    window_hash, start = words.runs(min_words)
    if not len(start):
        return start, window_hash, window_hash, start
    seed_hash, seed_at = words.runs(seed_words)
    full = np.full(len(words), ~U64(0), U64)
    full[seed_at] = seed_hash
    rank = np.full(len(words), ~U64(0), U64)
    rank[seed_at] = (mix(seed_hash, 5) & ~_PLACE) | (_PLACE - seed_at.astype(U64))
    place = (_PLACE - (sliding_least(rank, min_words - seed_words + 1)[start] & _PLACE)).astype(np.int64)
    return start, window_hash, full[place], place


def equal_neighbours(anchor: np.ndarray, window: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each (seed, window) entry whether another is equal, and whether it is the first of its equals."""
    order = np.argsort(mix(anchor ^ (window * U64(0x9FB21C651E98DF25)), 9), kind="stable")
    a, w = anchor[order], window[order]
    same = (a[1:] == a[:-1]) & (w[1:] == w[:-1])
    again = np.zeros(len(order), bool)
    first = np.ones(len(order), bool)
    again[order[1:]] |= same
    again[order[:-1]] |= same
    first[order[1:]] = ~same
    return again, first


def _pack(*arrays: np.ndarray) -> bytes:
    return np.array([a.nbytes for a in arrays], np.int64).tobytes() + b"".join(a.tobytes() for a in arrays)


_KINDS = (np.int64, np.int64, np.uint32, np.uint32, np.uint16, U64, np.uint32, np.uint16, np.uint32, np.uint32, np.uint32)


def _unpack(blob: bytes) -> list[np.ndarray]:
    sizes = np.frombuffer(blob, np.int64, len(_KINDS))
    at, out = 8 * len(_KINDS), []
    for kind, size in zip(_KINDS, sizes):
        out.append(np.frombuffer(blob, kind, int(size) // np.dtype(kind).itemsize, at))
        at += int(size)
    return out


def _breaks(*columns: np.ndarray) -> np.ndarray:
    """Indices where a new run of equal rows begins."""
    n = len(columns[0])
    if not n:
        return np.zeros(0, np.int64)
    new = np.ones(n, bool)
    new[1:] = False
    for c in columns:
        new[1:] |= c[1:] != c[:-1]
    return np.flatnonzero(new)


def _runs(text: np.ndarray, start: np.ndarray, *more: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of windows that follow each other: their first index and length."""
    head = _breaks(text, start - np.arange(len(start)), *more)
    return head, np.diff(np.append(head, len(start)))


def _chunks(buckets: int, min_words: int, seed_words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in arrowkit.gathered(batches, "text", CHUNK_BYTES):
            ids = part.column("doc_id").fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64)
            keys = part.column("text_key").to_numpy(zero_copy_only=False)
            words = arrowkit.Words(part.column("text"))
            start, window, seed, place = seeds(words, min_words, seed_words)
            if not len(start):
                continue
            text = np.searchsorted(words.first, start, side="right") - 1
            start = start - words.first[text]
            window = window & _LOW48
            again, first = equal_neighbours(seed, window)
            bucket = (mix(seed, 21) % U64(buckets)).astype(np.int32)
            order = np.argsort(bucket, kind="stable")
            edges = np.searchsorted(bucket[order], np.arange(buckets + 1))
            blobs, numbers = [], []
            for b in range(buckets):
                mine = order[edges[b]:edges[b + 1]]
                if not len(mine):
                    continue
                send = mine[first[mine]]
                known = mine[again[mine]]
                head, length = _runs(text[send], start[send], place[send])
                k_head, k_length = _runs(text[known], start[known])
                docs, number = np.unique(np.concatenate((text[send][head], text[known][k_head])), return_inverse=True)
                w = window[send]
                blobs.append(_pack(
                    ids[docs], keys[docs], number[:len(head)].astype(np.uint32), start[send][head].astype(np.uint32), length.astype(np.uint16), seed[send][head], (w & U64(0xFFFFFFFF)).astype(np.uint32), (w >> U64(32)).astype(np.uint16),
                    number[len(head):].astype(np.uint32), start[known][k_head].astype(np.uint32), k_length.astype(np.uint32),
                ))
                numbers.append(b)
            yield pa.RecordBatch.from_arrays([pa.array(numbers, pa.int32()), pa.array(blobs, pa.binary())], names=["bucket", "packed"])

    return run


def _meet(min_words: int):
    """Within one bucket after another: which windows occur twice, as spans of words."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bucket, blobs = -1, []
        for batch in batches:
            for b, blob in zip(batch.column("bucket").to_pylist(), batch.column("packed")):
                if b != bucket:
                    yield from close(blobs)
                    bucket, blobs = b, []
                blobs.append(blob.as_py())
        yield from close(blobs)

    def close(blobs: list[bytes]) -> Iterator[pa.RecordBatch]:
        held = [[] for _ in _KINDS]
        docs = 0
        for blob in blobs:
            got = _unpack(blob)
            got[2], got[8] = got[2] + np.uint32(docs), got[8] + np.uint32(docs)
            docs += len(got[0])
            for kept, x in zip(held, got):
                kept.append(x)
        if not docs:
            return
        ids, keys, doc, start, length, seed, low, high, k_doc, k_start, k_length = map(np.concatenate, held)
        window = low.astype(U64) | (high.astype(U64) << U64(32))
        again, _ = equal_neighbours(np.repeat(seed, length), window)
        hit_doc, hit_start = np.repeat(doc, length)[again], (np.repeat(start, length) + ranges(length.astype(np.int64)))[again]
        head, size = _runs(hit_doc, hit_start)
        doc = np.concatenate((hit_doc[head], k_doc))
        lo = np.concatenate((hit_start[head], k_start)).astype(np.int32)
        hi = lo + np.concatenate((size, k_length)).astype(np.int32) + np.int32(min_words - 1)
        for at in range(0, len(doc), 100_000):
            cut = slice(at, at + 100_000)
            yield pa.RecordBatch.from_arrays([pa.array(ids[doc[cut]]), pa.array(keys[doc[cut]]), pa.array(lo[cut]), pa.array(hi[cut])], names=["doc_id", "text_key", "lo", "hi"])

    return run


def repeated_spans(docs: DataFrame, min_words: int = 35, seed_words: int = 8) -> DataFrame:
    """Spans [lo, hi) of words covered by repeated windows: doc_id, text_key, lo, hi.

    ``text_key`` is the hash of the text, so that rows that share a doc_id but
    not a text stay apart; a null doc_id stands as -1.  Spans of one document
    can overlap; their union is the set of its maximal repeats.
    """
    if not 1 <= seed_words <= min_words <= 1 << 16:
        raise ValueError("1 <= seed_words <= min_words <= 65536 is needed")
    n = parts(docs.sparkSession)
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_key"), "text")
    packed = source.mapInArrow(arrowkit.tidy(_chunks(n * BUCKETS_A_TASK, min_words, seed_words)), "bucket int, packed binary")
    return packed.repartition(n, "bucket").sortWithinPartitions("bucket").mapInArrow(arrowkit.tidy(_meet(min_words)), "doc_id long, text_key long, lo int, hi int")


def drop_repeats(docs: DataFrame, min_words: int = 35, seed_words: int = 8, full: bool = False) -> DataFrame:
    """Every document without the words of its repeated windows.

    Words are runs of bytes other than ASCII white space, unchanged.  Returns
    ``doc_id``, ``n_words``, ``n_removed``, ``kept_sha256`` (of the kept words
    joined by single spaces) and, with ``full``, all columns of ``docs`` too and
    that text (``kept_text``).  Null and empty texts have no words.  Rows that
    repeat as a whole repeat each other's windows.  Raises unless
    1 <= seed_words <= min_words <= 65536.
    """
    names = [c for c in docs.columns if full or c in ("doc_id", "text")]
    row = docs.select(*names).withColumn("__id", F.coalesce(F.col("doc_id").cast("long"), F.lit(-1))).withColumn("__key", F.xxhash64("text"))
    spans = repeated_spans(docs, min_words, seed_words).groupBy(F.col("doc_id").alias("__id"), F.col("text_key").alias("__key")).agg(F.collect_list("lo").alias("__lo"), F.collect_list("hi").alias("__hi"))
    joined = row.join(spans, ["__id", "__key"], "left").drop("__id", "__key")
    kept_names = [c for c in joined.columns if c not in ("__lo", "__hi") and (full or c == "doc_id")]
    fields = {f.name: f.dataType.simpleString() for f in joined.schema.fields}
    schema = ", ".join([f"`{c}` {fields[c]}" for c in kept_names] + ["n_words long", "n_removed long", "kept_sha256 string"] + (["kept_text string"] if full else []))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in arrowkit.slices(batches, "text", 4 << 20):
            n_words, n_removed, sha, texts = [], [], [], []
            for text, lo, hi in zip(part.column("text"), part.column("__lo"), part.column("__hi")):
                words = (text.as_py() or "").encode().split()
                kept = words
                if lo.is_valid and len(lo):
                    edge = np.zeros(len(words) + 1, np.int64)
                    np.add.at(edge, lo.values.to_numpy(), 1)
                    np.add.at(edge, hi.values.to_numpy(), -1)
                    kept = [w for w, covered in zip(words, np.cumsum(edge)[:-1].tolist()) if not covered]
                joined = b" ".join(kept)
                n_words.append(len(words))
                n_removed.append(len(words) - len(kept))
                sha.append(hashlib.sha256(joined).hexdigest())
                if full:
                    texts.append(joined.decode())
            columns = [part.column(c) for c in kept_names] + [pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(sha, pa.string())] + ([pa.array(texts, pa.string())] if full else [])
            yield pa.RecordBatch.from_arrays(columns, names=[*kept_names, "n_words", "n_removed", "kept_sha256"] + (["kept_text"] if full else []))

    return joined.mapInArrow(arrowkit.tidy(run), schema)
