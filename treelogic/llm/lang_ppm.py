"""Language identification by prediction by partial matching over bytes.

Each language has a tree of byte contexts up to ``ORDER`` bytes deep with the
counts of the bytes that followed.  A byte's probability mixes the orders by
escaping: in a context seen t times with d different followers, a follower seen
c times has (c - 1/2) / t, and the escape to the context one byte shorter
(d / 2) / t; below the empty context all bytes are equally likely.  A text's
code length in a language is the sum of -log2 of its bytes' probabilities under
the frozen counts; the shortest code wins.

The counts are frozen after training, so a byte's code length depends on the
``ORDER`` bytes before it only.  A language is laid out as the sorted runs that
training showed, with their bytes' probabilities, and its contexts with their
escapes: the model is as large as what was seen, whatever the number of
languages, scripts and contexts.  A block of text is scored by its distinct runs.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treelogic.llm import arrowkit
from treelogic.llm.shared import checkpointed

ORDER = 3
#: Training bounds: documents and bytes for each language.
DOCS_A_LANGUAGE = 400
BYTES_A_LANGUAGE = 1_500_000
#: Languages up to which the table of their counts, which is counted, is broadcast.
BROADCAST_LANGUAGES = 50_000
UNKNOWN = "und"
_BLOCK = 1 << 19
#: A byte's number in a run is one above its value; 0 stands before a text's first byte.
_BITS = 9


@dataclass
class Tree:
    """One language: for each length of context the runs (context and follower) seen, and the contexts."""

    runs: list[np.ndarray]      # sorted codes of context and follower
    share: list[np.ndarray]     # (count - 1/2) / total of the context
    contexts: list[np.ndarray]  # sorted codes
    escape: list[np.ndarray]    # (kinds / 2) / total

    def probability(self, codes: np.ndarray) -> np.ndarray:
        """Of the last byte of each run of ORDER + 1 bytes after the bytes before it."""
        out = np.full(len(codes), 1 / 256)
        for length in range(ORDER + 1):
            code = codes & ((1 << _BITS * (length + 1)) - 1)
            at, known = _find(self.contexts[length], code >> _BITS)
            out[known] *= self.escape[length][at[known]]
            at, seen = _find(self.runs[length], code)
            out[seen] += self.share[length][at[seen]]
        return out


def _find(kept: np.ndarray, code: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of codes among the sorted ``kept``, and whether they are there."""
    if not len(kept):
        return np.zeros(len(code), np.int64), np.zeros(len(code), bool)
    at = np.minimum(np.searchsorted(kept, code), len(kept) - 1)
    return at, kept[at] == code


def _codes(data: np.ndarray, offsets: np.ndarray, lo: int, hi: int) -> np.ndarray:
    """The runs of ORDER + 1 bytes that end at the bytes lo to hi; none reaches before its text."""
    head = max(0, lo - ORDER)
    s = np.concatenate((np.zeros(ORDER - (lo - head), np.int64), data[head:hi].astype(np.int64) + 1))
    n = hi - lo
    begins = offsets[np.searchsorted(offsets, lo - ORDER, side="right"):np.searchsorted(offsets, hi)] - lo
    out = s[ORDER:].copy()
    for d in range(1, ORDER + 1):
        before = s[ORDER - d:ORDER - d + n].copy()
        for p in range(d):  # the first bytes of a text
            at = begins + p
            before[at[(at >= 0) & (at < n)]] = 0
        out |= before << (_BITS * d)
    return out


@dataclass
class PpmModel:
    """Frozen trees, by language."""

    languages: list[str]
    trees: list[Tree]
    usual: np.ndarray  # mean bits per byte of training texts in their own language

    def totals(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(texts x languages) code lengths in bits, and the texts' bytes."""
        data, offsets = arrowkit.as_bytes(column)
        n, texts = len(data), len(offsets) - 1
        out = np.zeros((texts, len(self.languages)))
        for lo in range(0, n, _BLOCK):  # blocks bound the memory for texts of any length
            hi = min(n, lo + _BLOCK)
            runs, which = np.unique(_codes(data, offsets, lo, hi), return_inverse=True)
            first = np.searchsorted(offsets, lo, side="right") - 1
            inside = offsets[first:np.searchsorted(offsets, hi) + 1]
            cuts = np.clip(inside[:-1], lo, hi) - lo
            full = np.flatnonzero(np.clip(inside[1:], lo, hi) - lo > cuts)
            for j, tree in enumerate(self.trees):
                bits = -np.log2(np.maximum(tree.probability(runs), 1e-12))
                if len(full):
                    out[first + full, j] += np.add.reduceat(bits[which], cuts[full])
        return out, np.diff(offsets)

    def predict(self, column: pa.Array) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Language, score (share of the likelihood that the best language has) and bits per byte."""
        total, size = self.totals(column)
        if not self.languages:
            return [UNKNOWN] * len(size), np.zeros(len(size)), np.zeros(len(size))
        best = total.argmin(axis=1)
        ahead = total - total[np.arange(len(best)), best][:, None]
        score = 1 / np.exp2(-np.minimum(ahead, 1000)).sum(axis=1)
        names = [self.languages[i] for i in best]
        for i, text in enumerate(column.to_pylist()):
            if text is None or not any(map(str.isalpha, text)):
                names[i], score[i] = UNKNOWN, 0.0
        return names, score, total[np.arange(len(best)), best] / np.maximum(size, 1)


def _grow(texts: list[bytes]) -> Tree:
    """The tree of a language's training texts."""
    tree = Tree([], [], [], [])
    data, offsets = arrowkit.as_bytes(pa.array(texts, pa.binary()))
    counts = [np.unique(_codes(data, offsets, lo, min(len(data), lo + _BLOCK)), return_counts=True) for lo in range(0, len(data), _BLOCK)]
    every = np.concatenate([c for c, _ in counts]) if counts else np.zeros(0, np.int64)
    weight = np.concatenate([w for _, w in counts]) if counts else np.zeros(0, np.int64)
    for length in range(ORDER + 1):
        code, where = np.unique(every & ((1 << _BITS * (length + 1)) - 1), return_inverse=True)
        seen = np.bincount(where, weights=weight, minlength=len(code))
        context, of, kinds = np.unique(code >> _BITS, return_inverse=True, return_counts=True)
        total = np.bincount(of, weights=seen, minlength=len(context))
        tree.runs.append(code)
        tree.share.append((seen - 0.5) / total[of] if len(code) else seen)
        tree.contexts.append(context)
        tree.escape.append(kinds / 2 / total if len(context) else total)
    return tree


def fit(texts: dict[str, list[bytes]]) -> PpmModel:
    """The model of labelled texts (language -> texts)."""
    languages = sorted(texts)
    model = PpmModel(languages, [_grow(texts[name]) for name in languages], np.zeros(len(languages)))
    for j, name in enumerate(languages):
        total, size = PpmModel([name], [model.trees[j]], model.usual).totals(pa.array(texts[name], pa.binary()))
        if len(size):
            model.usual[j] = (total[:, 0] / np.maximum(size, 1)).mean()
    return model


def training_rows(docs: DataFrame, docs_a_language: int = DOCS_A_LANGUAGE, bytes_a_language: int = BYTES_A_LANGUAGE) -> DataFrame:
    """(lang, text): whole texts of at most ``docs_a_language`` labelled rows of each language, in the order of a
    hash of the id, as long as those before hold less than ``bytes_a_language``.

    The choice depends on the rows alone, not on how they are dealt.  A language's
    rows are first thinned by the hash to about twice the wanted number, so that no
    task gets a language as a whole.  Ties of the hash go by id and by text.
    """
    rows = docs.filter("lang is not null and text is not null").select("lang", "text", F.xxhash64("doc_id").alias("h"), F.coalesce(F.col("doc_id").cast("long"), F.lit(-1)).alias("id"))
    sizes = checkpointed(rows.groupBy("lang").agg(F.count("*").alias("n")))
    if sizes.count() <= BROADCAST_LANGUAGES:  # else the texts would be dealt by language
        sizes = F.broadcast(sizes)
    place = (F.col("h").cast("double") + F.lit(2.0**63)) / F.lit(2.0**64)
    # a share of 2 m / n of uniform hashes holds m of n for all but a negligible chance; small languages are kept whole
    share = F.least(F.lit(1.0), F.lit(2.0 * docs_a_language + 100) / F.col("n"))
    few = rows.join(sizes, "lang").filter(place <= share).select("lang", "h", "id", F.octet_length("text").alias("size"), F.xxhash64("text").alias("key"), "text")
    order = Window.partitionBy("lang").orderBy("h", "id", "key")
    before = F.coalesce(F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    chosen = few.withColumn("r", F.row_number().over(order)).withColumn("before", before)
    return chosen.filter((F.col("r") <= docs_a_language) & (F.col("before") < bytes_a_language)).select("lang", "r", "text")


def train(docs: DataFrame, docs_a_language: int = DOCS_A_LANGUAGE, bytes_a_language: int = BYTES_A_LANGUAGE) -> PpmModel:
    """Fits on a bounded sample of the labelled rows: whole texts in a fixed order."""
    rows = sorted((r["lang"], r["r"], r["text"].encode()) for r in training_rows(docs, docs_a_language, bytes_a_language).toLocalIterator())
    texts: dict[str, list[bytes]] = {}
    for lang, _, text in rows:
        texts.setdefault(lang, []).append(text)
    del rows
    model = fit(texts)
    arrowkit.give_back()
    return model


def identify(docs: DataFrame, model: PpmModel, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` and ``lang_pred``, ``score`` (0 to 1), ``bits_per_byte``, ``excess`` of every whole text.

    ``excess``: the bits per byte above those that are usual in the language, which
    tell text of a language that was not learned.  A null text, or one without a letter, is ``und`` with
    score 0 and excess 0; ties go to the first language by name.  Each row is
    handled alone, so repeated rows have equal answers.  Narrow: no shuffle; the
    model, of as many runs as the bounded training texts hold, is broadcast.
    """
    names = [*keep]
    own = text if text in names else "__text"
    source = docs.select(*names) if text in names else docs.select(*names, F.col(text).alias("__text"))
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema if f.name in names] + ["lang_pred string", "score double", "bits_per_byte double", "excess double"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        at = {name: i for i, name in enumerate(m.languages)}
        for part in arrowkit.slices(batches, own, 1 << 20):
            lang, score, rate = m.predict(part.column(own))
            excess = [r - m.usual[at[x]] if x in at else 0.0 for x, r in zip(lang, rate)]
            yield pa.RecordBatch.from_arrays([*[part.column(c) for c in names], pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(rate, pa.float64()), pa.array(excess, pa.float64())], names=[*names, "lang_pred", "score", "bits_per_byte", "excess"])

    return source.mapInArrow(arrowkit.tidy(run), schema)


def held_out(doc_id: str = "doc_id"):
    """The documents that training leaves out: crc32 of the id as text, modulo 3, is 1."""
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 3 == 1


def predict_held_out(docs: DataFrame) -> DataFrame:
    """Trains on the labelled rows that are not held out and predicts every document."""
    out = F.coalesce(held_out(), F.lit(False))
    model = train(docs.filter(~out))
    return identify(docs, model).select("doc_id", out.alias("held_out"), "lang_pred", "score", "bits_per_byte", "excess")
