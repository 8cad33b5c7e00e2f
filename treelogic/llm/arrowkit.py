"""Vectorised text helpers shared by the operators of this folder.

Texts arrive in Arrow batches.  They are cut into slices of bounded size and
handled as one byte buffer with offsets, so that word and shingle hashes cost a
few numpy passes and no per-word Python work.  All hashes are functions of the
bytes alone: every executor computes the same ones.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U64 = np.uint64
#: Words up to this many bytes are hashed eight bytes at a time for a whole batch, longer ones one by one.
LONG_WORD = 256
#: Spans of up to this many bytes and of equal size have equal hashes only if they are equal: one bijection of them.
EXACT_BYTES = 8
_LOW_BYTES = np.array([(1 << 8 * i) - 1 for i in range(8)] + [2**64 - 1], U64)


def mix(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every bit (xor-shift and multiply)."""
    x = x + U64((seed * 0x632BE59BD9B4E019 + 0x1B873593) & (2**64 - 1))
    x ^= x >> U64(30)
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


def chain(before: np.ndarray, value: np.ndarray, seed: int) -> np.ndarray:
    """A hash of two hashes in order; linear in neither, so that no pattern of two words can cancel out."""
    return mix(mix(before, seed) ^ value, seed + 1)


@lru_cache(maxsize=1)
def _space_table() -> np.ndarray:
    out = np.zeros(256, bool)
    out[[9, 10, 11, 12, 13, 32]] = True
    return out


@lru_cache(maxsize=1)
def _fold_table() -> np.ndarray:
    out = np.arange(256, dtype=np.uint8)
    out[65:91] += 32
    return out


_kept: dict = {}
_owner: str | None = None


def kept(name, make):
    """What ``make`` gives, kept in the worker from task to task.

    Workers live on and serve one operator after another, so only one operator's
    things are kept at a time: ``tidy`` drops those of the one before.
    """
    if name not in _kept:
        _kept[name] = make()
    return _kept[name]


def _claim(owner: str) -> None:
    global _owner
    if owner != _owner:
        _owner = owner
        if _kept:
            _kept.clear()
            give_back()


def tidy(run):
    """The same function over batches; afterwards memory that it no longer uses goes back to the system.

    Workers live on between tasks, and the C library keeps what was freed.  The
    session's Arrow batches are bounded too: by default they hold 64 MB.
    """
    _bound_batches()
    owner = run.__module__

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _claim(owner)
        try:
            yield from run(batches)
        finally:
            give_back()

    return wrapped


def _bound_batches(most: int = 4 << 20) -> None:
    from pyspark.sql import SparkSession

    spark, name = SparkSession.getActiveSession(), "spark.sql.execution.arrow.maxBytesPerBatch"
    if spark is not None and spark.conf.get(name).rstrip("b") == str(64 << 20):  # as it comes
        spark.conf.set(name, str(most))


def give_back() -> None:
    """Returns freed memory to the system."""
    import ctypes

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def slices(batches: Iterable[pa.RecordBatch], column: str, most: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of at most ``most`` bytes of ``column`` (one row at least)."""
    for batch in batches:
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
        total = np.cumsum(sizes, dtype=np.int64)
        at = 0
        while at < batch.num_rows:
            base = total[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(total, base + most, side="right")))
            yield batch.slice(at, to - at)
            at = to


def gathered(batches: Iterable[pa.RecordBatch], column: str, most: int) -> Iterator[pa.RecordBatch]:
    """Rows in batches of about ``most`` bytes of ``column``, joined from smaller ones."""
    held: list[pa.RecordBatch] = []
    size = 0
    for part in slices(batches, column, most):
        n = pc.sum(pc.fill_null(pc.binary_length(part.column(column)), 0)).as_py() or 0
        if held and size + n > most:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held, size = [], 0
        if part.num_rows:
            held.append(part)
            size += n
    if held:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def as_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """A string column as one uint8 buffer and the n + 1 offsets of its rows; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_binary()), b"")
    n = len(column)
    offsets = np.frombuffer(column.buffers()[1], np.int64, n + 1, column.offset * 8)
    data = column.buffers()[2]
    whole = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return whole[offsets[0]:offsets[-1]], offsets - offsets[0]


def hash_spans(data: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span of bytes.

    Eight bytes after eight bytes go through a bijection together with the hash so
    far; the hash is linear in no byte, so no pattern of letters makes two spans
    collide for certain.  Spans over ``LONG_WORD`` bytes get BLAKE2b's.
    """
    size = stop - start
    out = mix(size.astype(U64), 1)
    if not len(out):
        return out
    padded = np.concatenate((data, np.zeros(8, np.uint8)))
    eight = np.ndarray((len(data) + 1,), "<u8", padded, 0, (1,))
    live = np.flatnonzero((size > 0) & (size <= LONG_WORD))
    at, left = start[live], size[live]
    while len(live):
        part = eight[at] & _LOW_BYTES[np.minimum(left, 8)]
        out[live] = mix(out[live] ^ part, 2)
        more = left > 8
        live, at, left = live[more], at[more] + 8, left[more] - 8
    for i in np.flatnonzero(size > LONG_WORD).tolist():
        out[i] = int.from_bytes(hashlib.blake2b(data[start[i]:stop[i]].tobytes(), digest_size=8).digest(), "little")
    return out


def distinct(values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The distinct values ascending, where each stands first, and for every value its place among them."""
    import pandas as pd

    code, found = pd.factorize(values)  # by a hash table, in the order of appearance
    fresh = np.ones(len(code), bool)
    if len(code):
        fresh[1:] = code[1:] > np.maximum.accumulate(code)[:-1]
    order = np.argsort(found)
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    return found[order], np.flatnonzero(fresh)[order], rank[code]


def same_spans(a: np.ndarray, a_start: np.ndarray, b: np.ndarray, b_start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Whether each span of ``a`` holds the same bytes as the span of equal size of ``b``."""
    out = np.ones(len(size), bool)
    views = [np.ndarray((len(x) + 1,), "<u8", np.concatenate((x, np.zeros(8, np.uint8))), 0, (1,)) for x in (a, b)]
    live = np.flatnonzero((size > 0) & (size <= LONG_WORD))
    i, j, left = a_start[live], b_start[live], size[live]
    while len(live):
        differ = (views[0][i] ^ views[1][j]) & _LOW_BYTES[np.minimum(left, 8)] != 0
        out[live[differ]] = False
        more = (left > 8) & ~differ
        live, i, j, left = live[more], i[more] + 8, j[more] + 8, left[more] - 8
    for k in np.flatnonzero(size > LONG_WORD).tolist():
        out[k] = np.array_equal(a[a_start[k]:a_start[k] + size[k]], b[b_start[k]:b_start[k] + size[k]])
    return out


def word_heads(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Which bytes begin a word of a text."""
    word = ~_space_table()[data]
    head = word.copy()
    if len(data) > 1:
        head[1:] &= ~word[:-1]
    begins = offsets[:-1][offsets[:-1] < offsets[1:]]
    head[begins] = word[begins]
    return head


def word_counts(column: pa.Array) -> np.ndarray:
    """Number of words of each text."""
    data, offsets = as_bytes(column)
    return np.diff(np.searchsorted(np.flatnonzero(word_heads(data, offsets)), offsets))


class Words:
    """The words (runs of bytes other than ASCII white space) of a batch of texts.

    ``hash`` holds a 64-bit hash of every word in order, ``first`` the n + 1
    offsets of the texts' words.
    """

    def __init__(self, column: pa.Array, fold: bool = False):
        data, offsets = as_bytes(column)
        if fold:
            data = _fold_table()[data]
        head = word_heads(data, offsets)
        start = np.flatnonzero(head)
        del head
        # a word ends before white space, at the next text, or at the end
        space = _space_table()[data]
        stop_mark = np.zeros(len(data) + 1, bool)
        if len(data) > 1:
            stop_mark[1:-1] = space[1:] & ~space[:-1]
        stop_mark[offsets[1:]] = True
        stops = np.flatnonzero(stop_mark)
        del space, stop_mark
        self.first = np.searchsorted(start, offsets)
        self.hash = hash_spans(data, start, stops[np.searchsorted(stops, start, side="right")] if len(start) else start)

    def __len__(self) -> int:
        return len(self.hash)

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def runs(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all runs of k words inside one text, and the index of each run's first word."""
        n = len(self.hash)
        counts = self.counts
        fit = np.maximum(counts - k + 1, 0)
        keep = np.repeat(self.first[:-1], fit) + ranges(fit)
        if not len(keep):
            return np.zeros(0, U64), keep
        return mix(self._joined(k)[keep], k), keep

    def _joined(self, k: int) -> np.ndarray:
        """Hashes of the runs of k words from every word on, over the borders of texts too: runs of
        1, 2, 4, ... words are made of two of half the length, and k is put together from these."""
        power, width, done, out = self.hash, 1, 0, None
        while True:
            if k & width:
                # ``out`` covers the ``done`` words before this piece
                out = power if out is None else chain(out[:len(power) - done], power[done:], 200 + width)
                done += width
            if done == k:
                return out[:len(self.hash) - k + 1]
            power = chain(power[:-width], power[width:], 100 + width)
            width *= 2

    def shingle_sets(self, k: int) -> list[np.ndarray]:
        """For each text the sorted distinct hashes of its k-word runs.

        A text of 1 to k - 1 words has one shingle, the whole sequence; a text
        without words has none.
        """
        runs, _ = self.runs(k)
        counts = self.counts
        fit = np.maximum(counts - k + 1, 0)
        at = np.concatenate(([0], np.cumsum(fit)))
        out = []
        for i, n in enumerate(counts):
            if n >= k:
                out.append(np.unique(runs[at[i]:at[i + 1]]))
            elif n:
                out.append(self._whole(i, int(n)))
            else:
                out.append(np.zeros(0, U64))
        return out

    def _whole(self, i: int, n: int) -> np.ndarray:
        value = np.array([n], U64)
        for h in self.hash[self.first[i]:self.first[i] + n]:
            value = chain(value, h, 300)
        return mix(value, 1000 + n)


def ranges(counts: np.ndarray) -> np.ndarray:
    """0..c-1 for every c of counts, one after the other."""
    total = int(counts.sum())
    if not total:
        return np.zeros(0, np.int64)
    ends = np.cumsum(counts)
    return np.arange(total) - np.repeat(ends - counts, counts)


def list_of(values: list[np.ndarray], kind: pa.DataType) -> pa.Array:
    """A list column from numpy arrays."""
    lengths = np.fromiter(map(len, values), np.int64, len(values))
    flat = np.concatenate(values) if values else np.zeros(0)
    return pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(lengths))).astype(np.int32)), pa.array(flat.view(np.int64) if flat.dtype == U64 else flat, kind))
