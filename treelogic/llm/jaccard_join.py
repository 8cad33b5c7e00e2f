"""Exact Jaccard self-join of word shingle sets, by prefixes under several token orders.

Order a set's shingles by any global order: two sets whose Jaccard similarity
reaches the threshold share a shingle within the first n - ceil(t n) + 1 of
each.  That holds for every order, so the filters of several orders may be
intersected.  Here all orders put rare shingles first (by a table of counters of
fixed size filled from every document); they differ in how coarsely they tell
rare from common and in how they arrange the rest.

1. Sets that are equal are one node, named by a hash of the set.
2. Each node sends its prefix shingles under every order.  Where only one node
   has a shingle it leads nowhere and is dropped; a node that keeps no shingle
   under one of the orders has no partner and goes.
3. Nodes meet on the shingles kept under the first order.  In such a group a
   pair stays a candidate if the sizes allow it, if the shingles kept under the
   other orders intersect, and if the parity bits of the two sets differ in no
   more places than the sets may.  The group sends a spanning forest of its
   candidate pairs, not all pairs.
4. Forest pairs are verified on the whole sets and give components.  Trees of
   three or more nodes in which several components are left then send every
   candidate pair between different components; after these are verified no
   link can be missing.

Pairs inside a component need no test: the result is the components.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.llm import arrowkit
from treelogic.llm.arrowkit import U64, mix
from treelogic.llm.components import components
from treelogic.llm.shared import checkpointed, parts

#: The token orders: each groups the rarity scale by one of these steps and has its own hash order within.
STEPS = (1, 5, 8)
ORDERS = len(STEPS)
COUNTERS = 1 << 22
_SLICES = 64
#: Parity signatures have this many bits, doubled as long as the sets may differ in too many places for them.
SIGNATURE_BITS = 256
SIGNATURE_LEVELS = 6
#: Bits of the table of wanted representatives; when it fills up more sets travel, none is lost.
WANTED_BITS = 1 << 25
BLOOM_WORDS = 2
CHUNK_BYTES = 4 << 20
#: Groups and pairs that a task remembers, so as to send them once; beyond that it starts anew and may repeat some.
REMEMBERED = 100_000
_LAST = 2**63 - 1
_LOW48 = U64((1 << 48) - 1)


@dataclass(frozen=True)
class Threshold:
    """Similarity num / den, in whole numbers so that the test is exact."""

    num: int
    den: int

    def prefix(self, n: int) -> int:
        return n + (-self.num * n) // self.den + 1

    def sizes_fit(self, small, large):
        return small * self.den >= large * self.num

    def most_apart(self, total):
        """Most elements in which two sets of this total size may differ."""
        return total * (self.den - self.num) // (self.den + self.num)


def _set_keys(sets: list[np.ndarray]) -> np.ndarray:
    sizes = np.fromiter(map(len, sets), np.int64, len(sets))
    sums = np.zeros(len(sets), U64)
    full = np.flatnonzero(sizes)
    if len(full):
        flat = mix(np.concatenate([sets[i] for i in full]), 41)
        sums[full] = np.add.reduceat(flat, np.concatenate(([0], np.cumsum(sizes[full])[:-1])))
    return mix(sums + sizes.astype(U64) * U64(0xD6E8FEB86659FD93), 43)


def _level(limit: Threshold, n: int) -> int:
    """Level of a set's signature: unrelated sets must differ in more places of it than similar ones may."""
    level = 0
    while level < SIGNATURE_LEVELS - 1 and 0.4 * (SIGNATURE_BITS << level) < limit.most_apart(2 * n):
        level += 1
    return level


def _parity(tokens: np.ndarray, limit: Threshold) -> bytes:
    """For each place whether an odd number of the set's shingles falls on it; xor of the halves is the next lower level."""
    bits = SIGNATURE_BITS << _level(limit, len(tokens))
    return np.packbits((np.bincount((mix(tokens, 31) & U64(bits - 1)).astype(np.int64), minlength=bits) & 1).astype(bool)).tobytes()


def _describe(k: int, limit: Threshold):
    """Document rows (doc_id, text_key, n, key, signature) and rows of counters (slice, packed)."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(COUNTERS, np.uint32)
        names = ["doc_id", "text_key", "n", "key", "signature", "slice", "packed"]
        some = False
        for part in arrowkit.slices(batches, "text"):
            sets = arrowkit.Words(part.column("text"), fold=True).shingle_sets(k)
            size = np.fromiter(map(len, sets), np.int64, len(sets))
            key = _set_keys(sets).view(np.int64).copy()
            lone = size == 0
            if lone.any():  # no partner can have this name
                key[lone] = part.column("text_key").to_numpy(zero_copy_only=False)[lone] ^ part.column("doc_id").to_numpy(zero_copy_only=False)[lone]
            full = [s for s in sets if len(s)]
            if full:
                some = True
                which, times = np.unique((np.concatenate(full) & U64(COUNTERS - 1)).astype(np.int32), return_counts=True)
                counts[which] += times.astype(np.uint32)
            none = pa.nulls(len(sets))
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text_key"), pa.array(size), pa.array(key), pa.array([_parity(s, limit) for s in sets], pa.binary()), none.cast(pa.int32()), none.cast(pa.binary())], names=names)
        if some:
            press = zstandard.ZstdCompressor(level=1)
            blobs = [press.compress(c.tobytes()) for c in np.split(counts, _SLICES)]
            none = pa.nulls(_SLICES)
            yield pa.RecordBatch.from_arrays([*[none.cast(pa.int64())] * 4, none.cast(pa.binary()), pa.array(range(_SLICES), pa.int32()), pa.array(blobs, pa.binary())], names=names)

    return run


def _add_counters(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    width = COUNTERS // _SLICES
    sums: dict[int, np.ndarray] = {}
    loose = zstandard.ZstdDecompressor()
    for batch in batches:
        for s, blob in zip(batch.column("slice").to_pylist(), batch.column("packed")):
            sums[s] = sums.get(s, np.zeros(width, np.int64)) + np.frombuffer(loose.decompress(blob.as_py()), np.uint32)
    scale = [np.minimum(np.round(12 * np.log2(v + 1.0)), 255).astype(np.uint8).tobytes() for v in sums.values()]
    yield pa.RecordBatch.from_arrays([pa.array(sums, pa.int32()), pa.array(scale, pa.binary())], names=["slice", "packed"])


def _rarity(described: DataFrame) -> np.ndarray:
    """How common the shingles of each counter are, on a logarithmic scale of 0 to 255."""
    rows = described.filter("slice is not null").select("slice", "packed").repartition(min(_SLICES, parts(described.sparkSession)), "slice").mapInArrow(arrowkit.tidy(_add_counters), "slice int, packed binary").collect()
    width = COUNTERS // _SLICES
    out = np.zeros(COUNTERS, np.uint8)  # the one table that reaches the driver: its size is fixed
    for r in rows:
        out[r["slice"] * width:(r["slice"] + 1) * width] = np.frombuffer(r["packed"], np.uint8)
    return out


def _prefixes(k: int, limit: Threshold, buckets: int, table: np.ndarray):
    """Each chunk's prefix shingles under every order, packed by bucket."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for chunk in arrowkit.gathered(batches, "text", CHUNK_BYTES):
            seen: set[int] = set()
            held: list[np.ndarray] = []
            masks: list[np.ndarray] = []
            keys: list[int] = []
            size: list[int] = []
            for part in arrowkit.slices([chunk], "text"):
                sets = arrowkit.Words(part.column("text"), fold=True).shingle_sets(k)
                for s, key in zip(sets, _set_keys(sets).tolist()):
                    if not len(s) or key in seen:
                        continue
                    seen.add(key)
                    p = limit.prefix(len(s))
                    common = table[(s & U64(COUNTERS - 1)).astype(np.int64)]
                    member = np.zeros(len(s), np.uint8)  # a bit for each order whose prefix has the shingle
                    for order, step in enumerate(STEPS):
                        rank = (common // np.uint8(step)).astype(U64) << U64(56) | (mix(s, 100 + order) >> U64(8))
                        member[np.argpartition(rank, p - 1)[:p] if p < len(s) else slice(None)] |= np.uint8(1 << order)
                    some = np.flatnonzero(member)
                    held.append(s[some])
                    masks.append(member[some])
                    keys.append(key)
                    size.append(len(some))
            if not keys:
                continue
            token = mix(np.concatenate(held), 51)
            member = np.concatenate(masks)
            number = np.repeat(np.arange(len(keys), dtype=np.uint32), size)
            bucket = (token % U64(buckets)).astype(np.int32)
            at = np.argsort(bucket, kind="stable")
            edges = np.searchsorted(bucket[at], np.arange(buckets + 1))
            full = [b for b in range(buckets) if edges[b] < edges[b + 1]]
            names = np.array(keys, U64)
            blobs = []
            for b in full:
                rows = at[edges[b]:edges[b + 1]]
                nodes, place = np.unique(number[rows], return_inverse=True)
                t = token[rows] & _LOW48  # shortened names of shingles can add candidates, never lose one
                blobs.append(_pack(member[rows], names[nodes], (t & U64(0xFFFFFFFF)).astype(np.uint32), (t >> U64(32)).astype(np.uint16), place.astype(np.uint16 if len(nodes) <= 1 << 16 else np.uint32)))
            yield pa.RecordBatch.from_arrays([pa.array(full, pa.int32()), pa.array(blobs, pa.binary())], names=["bucket", "packed"])

    return run


def _pack(*arrays: np.ndarray) -> bytes:
    return np.array([a.nbytes for a in arrays], np.int64).tobytes() + b"".join(a.tobytes() for a in arrays)


def _unpack(blob: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(orders' bits, token, key) of the entries of a packed row."""
    sizes = np.frombuffer(blob, np.int64, 5)
    at = 40 + np.concatenate(([0], np.cumsum(sizes)))
    part = lambda i, kind: np.frombuffer(blob, kind, int(sizes[i]) // np.dtype(kind).itemsize, int(at[i]))
    member, names, low, high = part(0, np.uint8), part(1, U64), part(2, np.uint32), part(3, np.uint16)
    place = part(4, np.uint16 if len(names) <= 1 << 16 else np.uint32)
    return member, low.astype(U64) | high.astype(U64) << U64(32), names[place]


def _shared_tokens(buckets: int):
    """The entries whose token another key has too under that order, packed by bucket of the key: the
    first order's tokens, and the other orders' as places of a bit set."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, order, token = _twice(batches)
        if not len(key):
            return
        bucket = (mix(key, 33) % U64(buckets)).astype(np.int64)
        at = np.lexsort((order, key, bucket))
        key, order, token, bucket = key[at], order[at], token[at], bucket[at]
        edges = np.searchsorted(bucket, np.arange(buckets + 1))
        full = [b for b in range(buckets) if edges[b] < edges[b + 1]]
        blobs = []
        for b in full:
            part = slice(edges[b], edges[b + 1])
            nodes, where = np.unique(key[part], return_inverse=True)
            first = order[part] == 0
            t = token[part][first]
            others = ((order[part][~first].astype(np.uint16) - 1) * (BLOOM_WORDS * 64) + (mix(token[part][~first], 70) % U64(BLOOM_WORDS * 64)).astype(np.uint16)).astype(np.uint16)
            blobs.append(_pack(nodes, np.bincount(where[first], minlength=len(nodes)).astype(np.uint32), np.bincount(where[~first], minlength=len(nodes)).astype(np.uint32), (t & U64(0xFFFFFFFF)).astype(np.uint32), (t >> U64(32)).astype(np.uint16), others))
        yield pa.RecordBatch.from_arrays([pa.array(full, pa.int32()), pa.array(blobs, pa.binary())], names=["bucket", "packed"])

    return run


def _twice(batches: Iterator[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(key, order, token) of the entries of all packed rows whose token two keys have under the order."""
    members, tokens, keys = [], [], []
    for batch in batches:
        for blob in batch.column("packed"):
            for kept, x in zip((members, tokens, keys), _unpack(blob.as_py())):
                kept.append(x)
    if not keys:
        return (np.zeros(0, U64),) * 3
    member, token, key = np.concatenate(members), np.concatenate(tokens), np.concatenate(keys)
    members, tokens, keys = [], [], []  # not held twice while sorting
    # one sort for all orders: entries of a token side by side, equal keys together
    at = np.lexsort((key, token))
    member, token, key = member[at], token[at], key[at]
    del at
    out = []
    for order in range(ORDERS):
        mine = np.flatnonzero(member >> np.uint8(order) & np.uint8(1))
        t, k = token[mine], key[mine]
        fresh = np.ones(len(t), bool)
        fresh[1:] = (t[1:] != t[:-1]) | (k[1:] != k[:-1])
        t, k = t[fresh], k[fresh]
        twice = np.zeros(len(t), bool)
        same = t[1:] == t[:-1]
        twice[1:] |= same
        twice[:-1] |= same
        out.append((k[twice], np.full(int(twice.sum()), order, np.uint8), t[twice]))
    return tuple(np.concatenate(x) for x in zip(*out))


def _by_key(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The keys that have entries under every order, with the first order's tokens and a bit set of
    the other orders' tokens."""
    kinds = (U64, np.uint32, np.uint32, np.uint32, np.uint16, np.uint16)
    held: list[list[np.ndarray]] = [[] for _ in kinds]
    for batch in batches:
        for blob in batch.column("packed").to_pylist():
            sizes = np.frombuffer(blob, np.int64, len(kinds))
            at = 8 * len(kinds)
            for kept, kind, size in zip(held, kinds, sizes.tolist()):
                kept.append(np.frombuffer(blob, kind, size // np.dtype(kind).itemsize, at))
                at += size
    if not held[0]:
        return
    key, firsts, others, low, high, place = map(np.concatenate, held)
    width = BLOOM_WORDS * 64
    nodes, where = np.unique(key, return_inverse=True)
    owner = np.repeat(where, firsts)
    order = np.argsort(owner, kind="stable")
    token = (low.astype(U64) | high.astype(U64) << U64(32)).view(np.int64)[order]
    edges = np.searchsorted(owner[order], np.arange(len(nodes) + 1))
    bloom = np.zeros((len(nodes), ORDERS - 1, width), bool)
    of = np.repeat(where, others)
    bloom[of, place // width, place % width] = True
    good = np.flatnonzero((np.diff(edges) > 0) & bloom.any(axis=2).all(axis=1))
    packed = np.packbits(bloom, axis=2)
    for i in range(0, len(good), 20_000):
        some = good[i:i + 20_000]
        yield pa.RecordBatch.from_arrays([pa.array(nodes[some].view(np.int64)), arrowkit.list_of([token[edges[j]:edges[j + 1]] for j in some.tolist()], pa.int64()), pa.array([packed[j].tobytes() for j in some.tolist()], pa.binary())], names=["key", "tokens", "bloom"])


class _Group:
    """The nodes that share one shingle, and the candidate test between them."""

    def __init__(self, limit: Threshold, key, n, bloom, signatures: list[bytes]):
        self.limit, self.key, self.n, self.bloom = limit, key, n, bloom
        size = np.fromiter(map(len, signatures), np.int64, len(signatures)) * 8 // SIGNATURE_BITS
        self.level = np.log2(size).astype(np.int64)
        #: for each level the signatures of the nodes that have it, folded down from their own
        self.signature = [np.zeros((len(key), (SIGNATURE_BITS << level) // 64), U64) for level in range(int(self.level.max()) + 1)]
        for i, (s, level) in enumerate(zip(signatures, self.level.tolist())):
            x = np.frombuffer(s, U64)
            while True:
                self.signature[level][i] = x
                if not level:
                    break
                x, level = x[:len(x) // 2] ^ x[len(x) // 2:], level - 1

    def candidates(self, i: int, others: np.ndarray) -> np.ndarray:
        """Those of ``others`` that may be similar to node i."""
        n, m = self.n[i], self.n[others]
        ok = self.limit.sizes_fit(np.minimum(n, m), np.maximum(n, m))
        others, m = others[ok], m[ok]
        if not len(others):
            return others
        for order in range(ORDERS - 1):
            ok = ((self.bloom[others, order] & self.bloom[i, order]) != 0).any(axis=1)
            others, m = others[ok], m[ok]
        apart = np.zeros(len(others), np.int64)
        level = np.minimum(self.level[others], self.level[i])
        for at in np.unique(level).tolist():
            mine = level == at
            apart[mine] = np.bitwise_count(self.signature[at][others[mine]] ^ self.signature[at][i]).sum(axis=1, dtype=np.int64)
        return others[apart <= self.limit.most_apart(n + m)]

    def forest(self) -> tuple[list[tuple[int, int]], list[int]]:
        """Spanning forest of the candidate pairs, and the nodes of its trees of three or more.

        Breadth first, nodes in the order of their documents.  Nodes of different
        trees are no candidates; of a tree of two all pairs are in the forest.
        """
        left = np.arange(len(self.key))
        out: list[tuple[int, int]] = []
        large: list[int] = []
        while len(left):
            queue, left = [int(left[0])], left[1:]
            before = len(out)
            root = queue[0]
            while queue and len(left):
                i = queue.pop()
                found = self.candidates(i, left)
                if len(found):
                    out += [(i, int(j)) for j in found]
                    left = np.setdiff1d(left, found, assume_unique=True)
                    queue += found.tolist()
            if len(out) > before + 1:
                large += [root, *(j for _, j in out[before:])]
        return out, large

    def between(self, root: np.ndarray) -> list[tuple[int, int]]:
        """Every candidate pair of different roots."""
        every = np.arange(len(self.key))
        return [(i, int(j)) for i in range(len(self.key) - 1) for j in self.candidates(i, every[i + 1:][root[i + 1:] != root[i]])]


def _pairs(limit: Threshold, across: bool):
    """Rows (a, b) of candidate pairs and, for the first round, rows (a, token) of the nodes to look at again."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()  # digests of the groups met, and pairs sent: to repeat less, not to be right
        sent: set[tuple[int, int]] = set()

        def close(rows: pa.Table):
            rows = rows.combine_chunks()
            token, key, n = (rows.column(c).to_numpy() for c in ("token", "key", "n"))
            root = rows.column("root").to_numpy() if across else None
            bloom = np.frombuffer(b"".join(rows.column("bloom").to_pylist()), U64).reshape(len(key), ORDERS - 1, BLOOM_WORDS)
            signature = rows.column("signature").to_pylist()
            head = np.flatnonzero(np.concatenate(([True], token[1:] != token[:-1])))
            found: list[tuple[int, int | None, int | None]] = []
            for i, j in zip(head.tolist(), [*head[1:].tolist(), len(token)]):
                if j - i < 2 or across and (root[i:j] == root[i]).all():
                    continue
                name = hashlib.blake2b(key[i:j].tobytes(), digest_size=12).digest()
                if name in seen:  # the same nodes met on another shingle
                    continue
                if len(seen) > REMEMBERED:
                    seen.clear()
                seen.add(name)
                group = _Group(limit, key[i:j], n[i:j], bloom[i:j], signature[i:j])
                pairs, again = (group.between(root[i:j]), []) if across else group.forest()
                for a, b in pairs:
                    pair = int(key[i + a]), int(key[i + b])
                    pair = pair if pair[0] < pair[1] else pair[::-1]
                    if pair not in sent:
                        if len(sent) > REMEMBERED:
                            sent.clear()
                        sent.add(pair)
                        found.append((*pair, None))
                found += [(int(key[i + a]), None, int(token[i])) for a in again]
            return pa.RecordBatch.from_arrays([pa.array([f[c] for f in found], pa.int64()) for c in range(3)], names=["a", "b", "token"])

        rest = None
        for batch in batches:
            now = pa.Table.from_batches([batch])
            now = pa.concat_tables([rest, now]) if rest is not None else now
            if not now.num_rows:
                continue
            token = now.column("token").to_numpy()
            last = int(np.argmax(token == token[-1]))  # the last group may go on
            rest = now.slice(last)
            if last:
                yield close(now.slice(0, last))
        if rest is not None and rest.num_rows:
            yield close(rest)

    return run


def _met(rows: DataFrame, limit: Threshold, n: int, across: bool) -> DataFrame:
    """What comes of the nodes (with ``token``) that meet on a shingle of the first order."""
    more = ["root"] if across else []
    rows = rows.select("token", "key", "rep", "n", "bloom", "signature", *more)
    rows = rows.repartition(n, "token").sortWithinPartitions("token", "rep", "key").drop("rep")
    return rows.mapInArrow(arrowkit.tidy(_pairs(limit, across)), "a long, b long, token long")


def _place(doc_id: np.ndarray, key: np.ndarray) -> np.ndarray:
    return (mix(doc_id.view(U64) ^ mix(key.view(U64), 90), 91) % U64(WANTED_BITS)).astype(np.int64)


def _wanted_bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    bits, some = np.zeros(WANTED_BITS // 8, np.uint8), False
    for batch in batches:
        some = some or batch.num_rows > 0
        place = _place(batch.column("rep").to_numpy(), batch.column("key").to_numpy())
        np.bitwise_or.at(bits, place >> 3, (128 >> (place & 7)).astype(np.uint8))
    if some:
        press = zstandard.ZstdCompressor(level=1)
        blobs = [press.compress(b.tobytes()) for b in np.split(bits, _SLICES)]
        yield pa.RecordBatch.from_arrays([pa.array(range(_SLICES), pa.int32()), pa.array(blobs, pa.binary())], names=["slice", "packed"])


def _join_bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    joined: dict[int, np.ndarray] = {}
    loose, press = zstandard.ZstdDecompressor(), zstandard.ZstdCompressor(level=1)
    for batch in batches:
        for s, blob in zip(batch.column("slice").to_pylist(), batch.column("packed")):
            bits = np.frombuffer(loose.decompress(blob.as_py()), np.uint8)
            joined[s] = joined[s] | bits if s in joined else bits
    yield pa.RecordBatch.from_arrays([pa.array(joined, pa.int32()), pa.array([press.compress(v.tobytes()) for v in joined.values()], pa.binary())], names=["slice", "packed"])


def _wanted(rows: DataFrame) -> np.ndarray:
    """Bit table of the (rep, key) rows; its size is fixed."""
    schema = "slice int, packed binary"
    found = rows.mapInArrow(arrowkit.tidy(_wanted_bits), schema).repartition(min(_SLICES, parts(rows.sparkSession)), "slice").mapInArrow(arrowkit.tidy(_join_bits), schema).collect()
    out = np.zeros(WANTED_BITS // 8, np.uint8)
    width = len(out) // _SLICES
    for r in found:
        out[r["slice"] * width:(r["slice"] + 1) * width] = np.frombuffer(zstandard.ZstdDecompressor().decompress(r["packed"]), np.uint8)
    return out


def _sets(k: int, wanted):
    """(key, tokens) of the texts whose doc_id and key are in the bit table."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = wanted.value
        for part in arrowkit.slices(batches, "text"):
            sets = arrowkit.Words(part.column("text"), fold=True).shingle_sets(k)
            key = _set_keys(sets).view(np.int64)
            place = _place(part.column("doc_id").to_numpy(), key)
            hit = np.flatnonzero((table[place >> 3] >> (7 - (place & 7)).astype(np.uint8)) & 1)
            if len(hit):
                yield pa.RecordBatch.from_arrays([pa.array(key[hit]), arrowkit.list_of([sets[i] for i in hit], pa.int64())], names=["key", "tokens"])

    return run


def similar_documents(docs: DataFrame, k: int = 5, num: int = 4, den: int = 5) -> DataFrame:
    """Classes of documents linked by Jaccard similarity num / den or more of their k-word shingle sets.

    Words are runs of bytes other than ASCII white space, A-Z lower-cased; a
    text with fewer than k words has one shingle; a text without words (or null)
    has none and no links.  Returns ``doc_id``, ``text_key`` (hash of the text),
    ``n_shingles``, ``component_id`` (least doc_id of the class) and ``keeper``
    (true on one row's doc_id and text_key of each class; rows that repeat as a
    whole all have it).  A null doc_id counts as the largest and comes back null.
    """
    limit, spark = Threshold(num, den), docs.sparkSession
    n = parts(spark)
    source = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST)).alias("doc_id"), F.xxhash64("text").alias("text_key"), "text")
    described = checkpointed(source.mapInArrow(arrowkit.tidy(_describe(k, limit)), "doc_id long, text_key long, n long, key long, signature binary, slice int, packed binary"))
    documents = described.filter("slice is null")
    classes = spark.sparkContext.broadcast(_rarity(described))  # COUNTERS bytes, whatever the input

    def prefixes(batches):
        return _prefixes(k, limit, n, classes.value)(batches)

    packed = source.select("text").mapInArrow(arrowkit.tidy(prefixes), "bucket int, packed binary")
    entries = packed.repartition(n, "bucket").mapInArrow(arrowkit.tidy(_shared_tokens(n)), "bucket int, packed binary")
    linked = entries.repartition(n, "bucket").mapInArrow(arrowkit.tidy(_by_key), "key long, tokens array<long>, bloom binary")
    distinct_sets = documents.filter("n > 0").groupBy("key").agg(F.min(F.struct("doc_id", "text_key")).alias("first"), F.min("n").alias("n"), F.min("signature").alias("signature"))
    nodes = checkpointed(linked.join(distinct_sets, "key").select("key", F.col("first.doc_id").alias("rep"), "n", "tokens", "bloom", "signature"))
    classes.destroy()  # what needed it is written

    side = nodes.select("key", "rep")

    def verified(pairs: DataFrame) -> tuple[DataFrame, DataFrame]:
        """The pairs, kept, and those of them that are links."""
        pairs = checkpointed(pairs)
        ends = pairs.select(F.col("a").alias("key")).union(pairs.select(F.col("b").alias("key"))).distinct().join(side, "key").select("rep", "key")
        wanted = spark.sparkContext.broadcast(_wanted(ends))  # WANTED_BITS bits, whatever the input
        sets = source.select("doc_id", "text").mapInArrow(arrowkit.tidy(_sets(k, wanted)), "key long, tokens array<long>").dropDuplicates(["key"])
        one = pairs.join(sets.select(F.col("key").alias("b"), F.col("tokens").alias("y")), "b")
        two = one.join(sets.select(F.col("key").alias("a"), F.col("tokens").alias("x")), "a")
        common = F.size(F.array_intersect("x", "y"))
        links = two.filter(common * (num + den) >= F.lit(num) * (F.size("x") + F.size("y"))).select("a", "b")
        links = checkpointed(links)
        wanted.destroy()
        return pairs, links

    met = checkpointed(_met(nodes.withColumn("token", F.explode("tokens")), limit, n, False))
    tried, first = verified(met.filter("b is not null").select("a", "b").distinct())
    roots = components(first)
    again = met.filter("b is null").select(F.col("a").alias("key"), "token").join(nodes, "key").join(roots.withColumnRenamed("a", "key"), "key", "left")
    more = _met(again.withColumn("root", F.coalesce("root", "key")), limit, n, True).select("a", "b").distinct()
    _, second = verified(more.join(tried, ["a", "b"], "left_anti"))
    roots = components(first.union(second))

    whole = distinct_sets.select("key", "first").join(roots.withColumnRenamed("a", "key"), "key", "left").withColumn("root", F.coalesce("root", "key"))
    heads = roots.join(distinct_sets.select(F.col("key").alias("a"), "first"), "a").groupBy("root").agg(F.min("first").alias("head"))
    named = whole.join(heads, "root", "left").select("key", F.coalesce("head", "first").alias("head"))
    out = documents.select("doc_id", "text_key", "n", "key").join(named, "key", "left")
    own = F.struct("doc_id", "text_key")
    head = F.coalesce("head", own)
    return out.select(
        F.when(F.col("doc_id") < _LAST, F.col("doc_id")).alias("doc_id"), "text_key", F.col("n").alias("n_shingles"),
        F.when(head["doc_id"] < _LAST, head["doc_id"]).alias("component_id"), (head == own).alias("keeper"),
    )
