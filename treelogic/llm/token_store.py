"""Token-id files: one wavelet matrix for each shard of documents.

A shard file holds the ids of consecutive documents as bit-planes, the highest
bit first; each plane is kept in the order left by stably sorting on the bits
above it.  With counts of ones per block the planes answer which token stands at
a place, how often a token occurs before it, and where its occurrences are,
without the ids ever being laid out.  All parts of the file are compressed one
by one and opened when asked for.

Layout (little-endian): 8 bytes magic; int64 tokens, documents, planes; for each
part its compressed size as int64; then the parts: document ids (int64), document
lengths (int64), zeros of each plane (int64), and each plane's bits.

Shards travel as rows (part, seq, first_doc, last_doc, n_docs, n_tokens, file) in
a Parquet table, so that any store that Spark can write holds them; ``export``
writes the same bytes as plain files where the driver can.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from treelogic.llm import arrowkit
from treelogic.llm.segment import library
from treelogic.llm.shared import bounds, parts, range_of, shared_folder

_MAGIC = b"TOKWAVE1"
_BLOCK = 512
SHARD_TOKENS = 4_000_000
#: Pre-tokens whose ids a worker keeps at most; beyond that the table starts anew.
KEPT_WORDS = 1_500_000


class WaveletMatrix:
    """Access, rank and select over a sequence of whole numbers."""

    def __init__(self, n: int, planes: list[np.ndarray], zeros: np.ndarray):
        self.n, self.planes, self.zeros = n, planes, zeros
        self._blocks: dict[int, np.ndarray] = {}

    @classmethod
    def build(cls, ids: np.ndarray, width: int | None = None) -> WaveletMatrix:
        if width is None:
            width = max(1, int(ids.max(initial=0)).bit_length())
        planes, zeros = [], []
        for bit in range(width - 1, -1, -1):
            one = (ids >> ids.dtype.type(bit)) & ids.dtype.type(1) == 1
            planes.append(np.packbits(one))
            low = ids[~one]
            zeros.append(len(low))
            ids = np.concatenate((low, ids[one]))
        return cls(len(ids), planes, np.array(zeros, np.int64))

    def tokens(self, kind=np.uint32) -> np.ndarray:
        """The whole sequence."""
        out = np.zeros(self.n, kind)
        width = len(self.planes)
        for level in range(width - 1, -1, -1):
            one = np.unpackbits(self.planes[level], count=self.n).view(bool)
            above = np.empty(self.n, kind)
            z = self.zeros[level]
            above[~one] = out[:z]
            above[one] = out[z:] | kind(1 << (width - 1 - level))
            out = above
        return out

    def _ones(self, level: int, i) -> np.ndarray:
        """Ones before each place of a plane."""
        if level not in self._blocks:
            counts = np.bitwise_count(np.pad(self.planes[level], (0, -len(self.planes[level]) % (_BLOCK // 8)))).reshape(-1, _BLOCK // 8).sum(axis=1, dtype=np.int64)
            self._blocks[level] = np.concatenate(([0], np.cumsum(counts)))
        i = np.asarray(i, np.int64)
        out = self._blocks[level][i // _BLOCK].copy()
        plane = self.planes[level]
        start = i // _BLOCK * (_BLOCK // 8)
        for step in range(_BLOCK // 8):  # whole bytes of the block, then the bits of the last
            byte = start + step
            whole = byte < i // 8
            if not whole.any():
                break
            out += np.where(whole, np.bitwise_count(plane[np.minimum(byte, len(plane) - 1)]), 0)
        rest = i % 8
        last = plane[np.minimum(i // 8, len(plane) - 1)] if len(plane) else np.zeros_like(i)
        return out + np.bitwise_count((last.astype(np.int64) >> (8 - rest)) & 0xFF)

    def _bit(self, level: int, i) -> np.ndarray:
        return (self.planes[level][i >> 3] >> (7 - (i & 7)).astype(np.uint8)) & 1

    def access(self, places) -> np.ndarray:
        """The tokens at the places."""
        i = np.atleast_1d(np.asarray(places, np.int64)).copy()
        if len(i) and (i.min() < 0 or i.max() >= self.n):
            raise IndexError("place outside the sequence")
        out = np.zeros(len(i), np.int64)
        for level in range(len(self.planes)):
            bit = self._bit(level, i).astype(bool)
            ones = self._ones(level, i)
            out = out * 2 + bit
            i = np.where(bit, self.zeros[level] + ones, i - ones)
        return out

    def _range(self, token: int, end: int) -> tuple[int, int]:
        """Where the token's occurrences before ``end`` stand in the order below the last plane."""
        width = len(self.planes)
        if token < 0 or token >> width:
            return 0, 0
        lo, hi = 0, end
        for level in range(width):
            ones = self._ones(level, [lo, hi])
            if token >> (width - 1 - level) & 1:
                lo, hi = (int(x) for x in self.zeros[level] + ones)
            else:
                lo, hi = lo - int(ones[0]), hi - int(ones[1])
        return lo, hi

    def rank(self, token: int, end: int) -> int:
        """Occurrences of the token before place ``end``."""
        lo, hi = self._range(token, min(max(end, 0), self.n))
        return hi - lo

    def count(self, token: int) -> int:
        return self.rank(token, self.n)

    def occurrences(self, token: int, first: int = 0, last: int | None = None) -> np.ndarray:
        """Places of the token's occurrences number ``first`` to ``last`` (not included), ascending."""
        lo, hi = self._range(token, self.n)
        at = np.arange(lo, hi)[first:last]
        width = len(self.planes)
        for level in range(width - 1, -1, -1):
            bits = np.unpackbits(self.planes[level], count=self.n)
            if token >> (width - 1 - level) & 1:
                at = np.flatnonzero(bits)[at - self.zeros[level]]
            else:
                at = np.flatnonzero(bits == 0)[at]
        return at

    def select(self, token: int, number: int) -> int:
        """Place of the token's occurrence ``number`` (from 0)."""
        found = self.occurrences(token, number, number + 1)
        if not len(found):
            raise IndexError("no such occurrence")
        return int(found[0])


class Shard:
    """A shard file: documents and their tokens."""

    def __init__(self, data: bytes):
        if data[:8] != _MAGIC:
            raise ValueError("not a token shard")
        self.n_tokens, self.n_docs, width = (int(x) for x in np.frombuffer(data, "<i8", 3, 8))
        sizes = np.frombuffer(data, "<i8", 3 + width, 32)
        self._at = 32 + 8 * len(sizes) + np.concatenate(([0], np.cumsum(sizes)))
        self._data = data
        self.doc_ids = np.frombuffer(self._part(0), "<i8")
        self.lengths = np.frombuffer(self._part(1), "<i8")
        self.matrix = WaveletMatrix(self.n_tokens, [np.frombuffer(self._part(3 + i), np.uint8) for i in range(width)], np.frombuffer(self._part(2), "<i8"))

    def _part(self, i: int) -> bytes:
        return zstandard.ZstdDecompressor().decompress(self._data[self._at[i]:self._at[i + 1]])

    @staticmethod
    def write(doc_ids: np.ndarray, lengths: np.ndarray, tokens: np.ndarray) -> bytes:
        matrix = WaveletMatrix.build(tokens)
        press = zstandard.ZstdCompressor(level=1)
        packed = [press.compress(x.tobytes()) for x in (doc_ids.astype("<i8"), lengths.astype("<i8"), matrix.zeros.astype("<i8"), *matrix.planes)]
        head = np.array([len(tokens), len(doc_ids), len(matrix.planes), *map(len, packed)], "<i8")
        return _MAGIC + head.tobytes() + b"".join(packed)

    def documents(self) -> Iterator[tuple[int, np.ndarray]]:
        """(doc_id, tokens) in order."""
        tokens = self.matrix.tokens()
        ends = np.cumsum(self.lengths)
        for doc, a, b in zip(self.doc_ids.tolist(), (ends - self.lengths).tolist(), ends.tolist()):
            yield doc, tokens[a:b]


# Bytes of the texts that are cut in bulk (ASCII without the apostrophe, and the letters of Latin-1).
_SPACE, _LETTER, _DIGIT, _OTHER, _FOREIGN = range(5)


@lru_cache(maxsize=1)
def _byte_class() -> np.ndarray:
    out = np.full(256, _FOREIGN, np.uint8)
    out[32:127] = _OTHER
    out[[9, 10, 11, 12, 13, 32]] = _SPACE
    out[48:58] = _DIGIT
    out[65:91] = out[97:123] = _LETTER
    out[39] = _FOREIGN
    return out


class BulkEncoder:
    """Ids of whole texts with the tokenizers library, for many texts at once.

    BPE works inside pre-tokens, so the library encodes each distinct pre-token
    once; a batch's pre-tokens are found, hashed and looked up as arrays.  Texts
    with other characters than ``_byte_class`` knows, or with a special token's
    mark, go to the library whole.
    """

    def __init__(self, path: str):
        self.library = library(path)
        vocab = self.library.get_vocab(with_added_tokens=True)
        self.kind = np.dtype("<u2") if max(vocab.values()) < 1 << 16 else np.dtype("<u4")
        self.last = np.zeros(max(vocab.values()) + 1, bool)
        for token, i in vocab.items():
            self.last[i] = token.endswith("</w>")
        self._reset()

    def _reset(self) -> None:
        self.known = np.zeros(0, arrowkit.U64)  # hashes of the pre-tokens, ascending, and their entries' numbers
        self.number = np.zeros(0, np.int32)
        self.letters = np.zeros(0, np.uint8)  # the pre-tokens' bytes, which a hash alone does not stand for
        self.letter_start = np.zeros(0, np.int64)  # in the order of ``known``
        self.letter_size = np.zeros(0, np.int64)
        self.start = np.zeros(1 << 16, np.int32)
        self.length = np.zeros(1 << 16, np.int32)
        self.flat = np.zeros(1 << 18, self.kind)
        self.n = self.used = 0

    def _library(self, text: str) -> np.ndarray:
        fast = getattr(self.library, "encode_batch_fast", self.library.encode_batch)  # without offsets, where there is one
        return np.array(fast([text], add_special_tokens=False)[0].ids, self.kind)

    def _append(self, ids: np.ndarray, lengths: np.ndarray) -> int:
        """New entries; returns the number of the first."""
        first = self.n
        while len(self.start) < self.n + len(lengths):
            self.start, self.length = np.resize(self.start, 2 * len(self.start)), np.resize(self.length, 2 * len(self.length))
        while len(self.flat) < self.used + len(ids):
            self.flat = np.resize(self.flat, 2 * len(self.flat))
        self.flat[self.used:self.used + len(ids)] = ids
        self.start[first:first + len(lengths)] = self.used + np.cumsum(lengths) - lengths
        self.length[first:first + len(lengths)] = lengths
        self.n += len(lengths)
        self.used += len(ids)
        return first

    def _learn(self, words: list[str]) -> int:
        ids = self._library(" ".join(words))
        ends = np.flatnonzero(self.last[ids]) + 1
        if len(ends) == len(words):
            return self._append(ids, np.diff(ends, prepend=0))
        each = [self._library(w) for w in words]  # a pre-token that is cut otherwise among others
        return self._append(np.concatenate(each), np.array([len(e) for e in each], np.int64))

    def encode(self, column: pa.Array, end_id: int | None, whole_texts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts one after the other, offsets of the texts); ``end_id`` ends each text.

        Pre-tokens are found by their hashes and compared byte by byte; texts in
        which two different ones share a hash go to the library (``whole_texts``).
        """
        data, offsets = arrowkit.as_bytes(column)
        texts = len(offsets) - 1
        kind = _byte_class()[data]
        after = np.flatnonzero(data == 0xC3) + 1
        after = after[after < len(data)]
        tail = data[after]
        good = (tail >= 0x80) & (tail <= 0xBF) & (tail != 0x97) & (tail != 0xB7)
        letters = after[good]
        kind[letters] = kind[letters - 1] = _LETTER
        foreign = np.concatenate((np.flatnonzero(kind == _FOREIGN), np.flatnonzero((data[:-1] == 60) & (data[1:] == 124)) if len(data) > 1 else np.zeros(0, np.int64)))
        odd = np.unique(np.searchsorted(offsets, foreign, side="right") - 1)
        if whole_texts is not None:
            odd = np.union1d(odd, whole_texts)
        data = arrowkit._fold_table()[data]
        upper = letters[data[letters] <= 0x9E]
        data[upper] += 0x20
        head = kind != _SPACE
        edge = np.ones(len(data), bool)
        if len(data):
            edge[1:] = (kind[1:] != kind[:-1]) | (kind[1:] == _DIGIT)
        begins = offsets[:-1][offsets[:-1] < offsets[1:]]
        edge[begins] = True
        edges = np.append(np.flatnonzero(edge), len(data))
        word = np.flatnonzero(head[edges[:-1]])
        # a pre-token ends at the next edge
        start, stop = edges[word], edges[word + 1]
        of_text = np.repeat(np.arange(texts), np.diff(np.searchsorted(start, offsets)))
        if len(odd):
            keep = ~np.isin(of_text, odd)
            start, stop, of_text = start[keep], stop[keep], of_text[keep]
        value, first, where = arrowkit.distinct(arrowkit.hash_spans(data, start, stop))
        if self.n + len(value) > KEPT_WORDS:
            self._reset()
        place = np.searchsorted(self.known, value)
        inside = np.minimum(place, max(len(self.known) - 1, 0))
        hit = self.known[inside] == value if len(self.known) else np.zeros(len(value), bool)
        size = stop - start
        here = start[first]
        same = (size == size[first][where]) if len(value) else np.zeros(0, bool)
        long = np.flatnonzero(same & (size > arrowkit.EXACT_BYTES))
        same[long] = arrowkit.same_spans(data, start[long], data, here[where[long]], size[long])
        if hit.any():
            at = inside[hit]
            agree = self.letter_size[at] == size[first[hit]]
            long = np.flatnonzero(agree & (self.letter_size[at] > arrowkit.EXACT_BYTES))
            agree[long] = arrowkit.same_spans(data, here[hit][long], self.letters, self.letter_start[at][long], self.letter_size[at][long])
            strange = np.zeros(len(value), bool)
            strange[np.flatnonzero(hit)[~agree]] = True
            same &= ~strange[where]
        if not same.all():
            return self.encode(column, end_id, np.union1d(odd, of_text[~same]))
        number = np.full(len(value), -1, np.int64)
        number[hit] = self.number[inside[hit]]
        fresh = np.flatnonzero(~hit)
        if len(fresh):
            raw = data.tobytes()
            base = self._learn([raw[a:b].decode() for a, b in zip(start[first[fresh]].tolist(), stop[first[fresh]].tolist())])
            number[fresh] = np.arange(base, base + len(fresh))
            held = size[first[fresh]]
            self.letter_start = np.insert(self.letter_start, place[fresh], len(self.letters) + np.cumsum(held) - held)
            self.letter_size = np.insert(self.letter_size, place[fresh], held)
            self.letters = np.concatenate((self.letters, data[np.repeat(here[fresh], held) + arrowkit.ranges(held)]))
            self.known = np.insert(self.known, place[fresh], value[fresh])
            self.number = np.insert(self.number, place[fresh], number[fresh])
        pieces = number[where]
        n, used = self.n, self.used  # what follows is kept for this batch only
        places, values = [], []
        bound = np.searchsorted(of_text, np.arange(texts), side="right")
        if len(odd):
            whole = [self._library(column[int(i)].as_py() or "") for i in odd]
            base = self._append(np.concatenate(whole), np.array([len(w) for w in whole], np.int64))
            places.append(bound[odd])
            values.append(np.arange(base, base + len(odd)))
        if end_id is not None:
            base = self._append(np.array([end_id], self.kind), np.array([1]))
            places.append(bound)
            values.append(np.full(texts, base))
        text_of = [np.asarray(odd)] * bool(len(odd)) + [np.arange(texts)] * (end_id is not None)
        if places:
            owner = np.concatenate(text_of)
            order = np.argsort(owner, kind="stable")
            pieces = np.insert(pieces, np.concatenate(places)[order], np.concatenate(values)[order])
            counts = np.bincount(of_text, minlength=texts) + np.bincount(owner, minlength=texts)
        else:
            counts = np.bincount(of_text, minlength=texts)
        size = self.length[pieces]
        ids = self.flat[np.repeat(self.start[pieces].astype(np.int64), size) + arrowkit.ranges(size)]
        ends = np.concatenate(([0], np.cumsum(size, dtype=np.int64)))
        self.n, self.used = n, used
        return ids, ends[np.concatenate(([0], np.cumsum(counts)))]


def _encoder(path: str) -> BulkEncoder:
    return arrowkit.kept(("bulk", path), lambda: BulkEncoder(path))


def _encode(path: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = _encoder(path)
        for part in arrowkit.slices(batches, "text", 2 << 20):
            ids, offsets = coder.encode(part.column("text"), end_id)
            if ids.nbytes >= 1 << 31:  # a slice holds more than 2 MB of text only if that is one document
                raise ValueError("the ids of one document take 2 GB or more, which a row cannot hold")
            packed = pa.Array.from_buffers(pa.binary(), part.num_rows, [None, pa.py_buffer((offsets * coder.kind.itemsize).astype(np.int32)), pa.py_buffer(np.ascontiguousarray(ids))])
            yield pa.RecordBatch.from_arrays([part.column("part"), part.column("doc_id"), packed], names=["part", "doc_id", "ids"])

    return run


def _shards(path: str, most: int):
    """Rows sorted by range and document become shard files."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = _encoder(path).kind
        part, seq, docs, packed, size = None, 0, [], [], 0

        def close() -> pa.RecordBatch:
            lengths = np.array([len(p) for p in packed], np.int64) // kind.itemsize
            tokens = np.frombuffer(b"".join(packed), kind)
            file = Shard.write(np.array(docs, np.int64), lengths, tokens)
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([seq], pa.int32()), pa.array([docs[0]], pa.int64()), pa.array([docs[-1]], pa.int64()), pa.array([len(docs)], pa.int64()), pa.array([len(tokens)], pa.int64()), pa.array([file], pa.binary())], names=["part", "seq", "first_doc", "last_doc", "n_docs", "n_tokens", "file"])

        for batch in batches:
            for p, doc, ids in zip(batch.column("part").to_pylist(), batch.column("doc_id").to_pylist(), batch.column("ids")):
                data = ids.as_py()
                if docs and (p != part or size + len(data) > most * kind.itemsize):
                    yield close()
                    seq, docs, packed, size = (seq + 1 if p == part else 0), [], [], 0
                part = p
                docs.append(doc)
                packed.append(data)
                size += len(data)
        if docs:
            yield close()

    return run


def write_store(docs: DataFrame, path: str, folder: str, end_id: int = 1, shard_tokens: int = SHARD_TOKENS) -> None:
    """Writes the documents' ids, in ascending doc_id order, as a table of shard files in ``folder``.

    ``end_id`` ends each document; a null text has only that.  A null doc_id
    counts as the least (-2**63); rows that share a doc_id are ordered by their ids,
    so rows that repeat as a whole stand side by side.  A document whose ids take
    2 GB or more is an error.  One shuffle, of packed ids; a shard is as large as ``shard_tokens``, or one document.
    """
    n = parts(docs.sparkSession)
    source = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(-2**63)).alias("doc_id"), "text")
    cuts = bounds(source, "doc_id", 2 * n)
    ids = source.select(range_of("doc_id", cuts).alias("part"), "doc_id", "text").mapInArrow(arrowkit.tidy(_encode(path, end_id)), "part int, doc_id long, ids binary")
    rows = ids.repartition(n, "part").sortWithinPartitions("part", "doc_id", "ids")
    rows.mapInArrow(arrowkit.tidy(_shards(path, shard_tokens)), "part int, seq int, first_doc long, last_doc long, n_docs long, n_tokens long, file binary").write.option("compression", "none").parquet(folder)


def read_store(spark: SparkSession, folder: str) -> DataFrame:
    return spark.read.parquet(folder)


def export(store: DataFrame, folder: str) -> int:
    """Writes each shard as a plain file in a folder the driver can reach, one at a time; returns their number."""
    import os

    os.makedirs(folder, exist_ok=True)
    n = 0
    for row in store.toLocalIterator():
        with open(os.path.join(folder, f"{row['part']:06d}-{row['seq']:06d}.wave"), "wb") as f:
            f.write(row["file"])
        n += 1
    return n


def documents_of(store: DataFrame) -> DataFrame:
    """Per document, read from the files: doc_id, start (tokens of all documents before it), n_tokens,
    ids_crc32 (of the ids as little-endian unsigned 32-bit integers)."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, seq, file in zip(*(batch.column(c) for c in ("part", "seq", "file"))):
                shard = Shard(file.as_py())
                crc = [zlib.crc32(tokens.astype("<u4", copy=False)) for _, tokens in shard.documents()]
                n = shard.n_docs
                yield pa.RecordBatch.from_arrays([pa.array([part.as_py()] * n, pa.int32()), pa.array([seq.as_py()] * n, pa.int32()), pa.array(shard.doc_ids), pa.array(np.cumsum(shard.lengths) - shard.lengths), pa.array(shard.lengths), pa.array(crc, pa.int64())], names=["part", "seq", "doc_id", "inside", "n_tokens", "ids_crc32"])

    rows = store.select("part", "seq", "file").mapInArrow(arrowkit.tidy(run), "part int, seq int, doc_id long, inside long, n_tokens long, ids_crc32 long")
    # one row for each shard: the running sum is over as many rows as there are files
    before = F.sum("n_tokens").over(Window.orderBy("part", "seq").rowsBetween(Window.unboundedPreceding, -1))
    bases = store.select("part", "seq", F.coalesce(before, F.lit(0)).alias("base"))
    doc = F.when(F.col("doc_id") > F.lit(-2**63), F.col("doc_id"))
    return rows.join(bases, ["part", "seq"]).select(doc.alias("doc_id"), (F.col("base") + F.col("inside")).alias("start"), "n_tokens", "ids_crc32")


def find_token(store: DataFrame, token: int) -> DataFrame:
    """(part, seq, occurrences, doc_ids): where a token occurs, from the planes alone."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for part, seq, file in zip(*(batch.column(c).to_pylist() for c in ("part", "seq", "file"))):
                shard = Shard(file)
                at = shard.matrix.occurrences(token)
                if len(at):
                    rows.append((part, seq, len(at), np.unique(shard.doc_ids[np.searchsorted(np.cumsum(shard.lengths), at, side="right")]).tolist()))
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.int64()), pa.array([r[3] for r in rows], pa.list_(pa.int64()))], names=["part", "seq", "occurrences", "doc_ids"])

    return store.select("part", "seq", "file").mapInArrow(arrowkit.tidy(run), "part int, seq int, occurrences long, doc_ids array<long>")


def round_trip(docs: DataFrame, path: str) -> DataFrame:
    """Writes a store in the shared folder and returns ``documents_of`` what is read back."""
    folder = f"{shared_folder(docs.sparkSession)}/token-store-{uuid.uuid4().hex}"
    write_store(docs, path, folder)
    return documents_of(read_store(docs.sparkSession, folder))
