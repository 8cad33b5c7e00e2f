"""Token counts of sections by the places of tokens in the whole document.

A document is encoded once, as a whole, and each token's span of bytes follows
from the tokens' lengths.  The spans are joined with the spans of the sections;
a token that lies across a border is given by rule:

- ``start``: to the section that holds its first byte;
- ``end``: to the section that holds its last byte;
- ``most``: to the section that holds most of its bytes, the earlier of equals;
- ``split``: to every section by its share of the bytes (a fraction).

Under the first three rules the sections' counts of a document sum to its
tokens; under ``split`` they do up to rounding.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.llm import arrowkit

RULES = ("start", "end", "most", "split")


def _encoding(path: str):
    return arrowkit.kept(("encoding", path), lambda: _load(path))


def _load(path: str):
    import public_tokenizers
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in f if line.strip())}
    size = np.zeros(max(ranks.values()) + 1, np.int64)
    for token, rank in ranks.items():
        size[rank] = len(token)
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}), size


def token_spans(text: str, path: str) -> tuple[np.ndarray, np.ndarray]:
    """(ids, ends): token i covers the bytes from the end of the one before to ends[i]."""
    encoding, size = _encoding(path)
    ids = np.array(encoding.encode_ordinary(text), np.int64)
    return ids, np.cumsum(size[ids]) if len(ids) else ids


def attribute(ends: np.ndarray, borders: np.ndarray, rule: str) -> np.ndarray:
    """Tokens of each section; section i covers the bytes from borders[i] to borders[i + 1], without gaps."""
    sections = len(borders) - 1
    starts = np.concatenate(([0], ends[:-1])) if len(ends) else ends
    first = np.searchsorted(borders, starts, side="right") - 1
    last = np.searchsorted(borders, ends - 1, side="right") - 1
    if rule == "start":
        return np.bincount(first, minlength=sections)
    if rule == "end":
        return np.bincount(last, minlength=sections)
    inside = first == last
    out = np.bincount(first[inside], minlength=sections).astype(float if rule == "split" else np.int64)
    for s, e, i, j in zip(starts[~inside].tolist(), ends[~inside].tolist(), first[~inside].tolist(), last[~inside].tolist()):
        held = [min(e, int(borders[k + 1])) - max(s, int(borders[k])) for k in range(i, j + 1)]
        if rule == "split":
            for k, h in enumerate(held):
                out[i + k] += h / (e - s)
        else:
            out[i + held.index(max(held))] += 1
    return out


def line_borders(data: np.ndarray) -> np.ndarray:
    """Borders of the lines of a text in bytes; a line holds its line feed."""
    after = np.flatnonzero(data == 10) + 1
    if len(after) and after[-1] == len(data):
        after = after[:-1]
    return np.concatenate(([0], after, [len(data)])).astype(np.int64)


def section_counts(docs: DataFrame, path: str, rule: str = "most", text: str = "text", sections: str | None = None) -> DataFrame:
    """Tokens of the sections of every whole text.

    Sections are lines, or, if ``sections`` names a column of ascending arrays of
    character offsets, what lies between these (the text before the first offset
    is a section too).  Returns doc_id, section (from 0), start_char, end_char,
    n_tokens (a double under ``split``) and doc_tokens, one row for each
    section.  A null or empty text has one empty section without tokens.
    Narrow: no shuffle, whole documents in batches of bounded size.
    """
    if rule not in RULES:
        raise ValueError(f"no such rule: {rule}")
    source = docs.select("doc_id", F.col(text).alias("text"), *([F.col(sections).cast("array<long>").alias("cuts")] if sections else []))
    kind = pa.float64() if rule == "split" else pa.int64()
    schema = f"doc_id {source.schema['doc_id'].dataType.simpleString()}, section int, start_char long, end_char long, n_tokens {'double' if rule == 'split' else 'long'}, doc_tokens long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in arrowkit.slices(batches, "text", 2 << 20):
            row, number, start, end, count, total = [], [], [], [], [], []
            texts = part.column("text").to_pylist()
            cuts = part.column("cuts").to_pylist() if sections else [None] * len(texts)
            for i, (value, cut) in enumerate(zip(texts, cuts)):
                value = value or ""
                data = np.frombuffer(value.encode(), np.uint8)
                lead = np.flatnonzero((data & 0xC0) != 0x80)  # place of each character's first byte
                if sections:
                    inner = sorted({int(c) for c in cut or [] if c is not None and 0 < c < len(value)})
                    borders = np.concatenate(([0], lead[inner] if inner else [], [len(data)])).astype(np.int64)
                else:
                    borders = line_borders(data)
                _, ends = token_spans(value, path)
                counts = attribute(ends, borders, rule)[:len(borders) - 1] if len(ends) else np.zeros(len(borders) - 1, np.int64)
                chars = np.searchsorted(lead, borders)
                n = len(borders) - 1
                row.append(np.full(n, i))
                number.append(np.arange(n, dtype=np.int32))
                start.append(chars[:-1])
                end.append(chars[1:])
                count.append(counts)
                total.append(np.full(n, len(ends)))
            if row:
                join = np.concatenate
                yield pa.RecordBatch.from_arrays([part.column("doc_id").take(pa.array(join(row))), pa.array(join(number)), pa.array(join(start), pa.int64()), pa.array(join(end), pa.int64()), pa.array(join(count), kind), pa.array(join(total), pa.int64())], names=["doc_id", "section", "start_char", "end_char", "n_tokens", "doc_tokens"])

    return source.mapInArrow(arrowkit.tidy(run), schema)
