"""Exact BPE by dynamic programming over prefixes, and its decoding.

BPE's encoding of a word has a useful property: each prefix of the word has one
encoding, and the last token of that encoding is unique.  So it is enough to
keep one token for each prefix.  An automaton over the vocabulary reports every
token that ends at the current place; such a token is the one if the last token
of what stands before it may be followed by it, that is, if encoding the two
tokens' joined text would give back just these two.  The ids are read off by
following the stored tokens back from the end.

``encode_texts`` is the operator; words repeat, so their ids are kept in a
bounded table in each worker.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.llm import arrowkit
from treelogic.llm.segment import Segmenter, byte_chars, mapped

#: Words whose ids a worker keeps at most, half of them new and half from before.
KEPT_WORDS = 100_000
_END = 0xE000


class PrefixBpe:
    """The vocabulary with what the dynamic programme asks of it."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        self.suffix = model["end_of_word_suffix"] or ""
        self.vocab: dict[str, int] = model["vocab"]
        self.strings = {i: t for t, i in self.vocab.items()}
        merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ", 1)) for m in model["merges"]]
        #: rank of the merge of two tokens, and the parts and rank of each merged token
        self.rank: dict[tuple[int, int], int] = {}
        self.parts: dict[int, tuple[int, int, int]] = {}
        for r, (a, b) in enumerate(merges):
            left, right, whole = self.vocab[a], self.vocab[b], self.vocab[a + b]
            self.rank[left, right] = r
            self.parts.setdefault(whole, (left, right, r))
        #: known answers of ``fits``, by both ids in one number
        self._fits: dict[int, bool] = {}
        self.automaton = self._automaton()

    def _symbols(self, token: str) -> str:
        """One character for each byte; a last byte with the end mark has its own."""
        if self.suffix and token.endswith(self.suffix):
            body = token[:-len(self.suffix)]
            return body[:-1] + chr(_END + ord(body[-1])) if body else ""
        return token

    def _automaton(self):
        import ahocorasick

        tree = ahocorasick.Automaton()
        reachable = set(self.parts)
        for token, i in self.vocab.items():
            symbols = self._symbols(token)
            if symbols and (len(symbols) == 1 or i in reachable):
                tree.add_word(symbols, (i, len(symbols)))
        tree.make_automaton()
        return tree

    def fits(self, a: int, b: int) -> bool:
        """Whether the tokens a, b stay apart when their joined text is encoded.

        Undo the later merge of the two step by step.  If at any step the two
        pieces that touch could have merged before one of them was made, the
        border would have been crossed.
        """
        known = self._fits.get(a << 32 | b)
        if known is None:
            if len(self._fits) > 200_000:
                self._fits.clear()
            known = self._fits[a << 32 | b] = self._stay_apart(a, b)
        return known

    def _stay_apart(self, a: int, b: int) -> bool:
        never = len(self.rank) + 1
        made_a = self.parts[a][2] if a in self.parts else -1
        made_b = self.parts[b][2] if b in self.parts else -1
        # the pieces exist side by side from max(made) on, until the end
        until = never
        while True:
            crossing = self.rank.get((a, b), never)
            # a crossing merge wins if it comes before the merge that replaces either piece;
            # of equal ranks the left one is made first
            if crossing < until:
                return False
            if made_a < 0 and made_b < 0:
                return True
            if made_a > made_b:  # of equal ranks the left one is made first, so b is undone first
                # undo a: its right part touched b until the merge made_a took it
                until = made_a
                a = self.parts[a][1]
                made_a = self.parts[a][2] if a in self.parts else -1
            else:
                # undo b: its left part touched a until the merge made_b took it; a crossing merge
                # of the same rank stands further left and is made first
                until = made_b + 1
                b = self.parts[b][0]
                made_b = self.parts[b][2] if b in self.parts else -1

    def encode_word(self, word: str) -> list[int]:
        """The ids of one pre-token in byte characters."""
        whole = self.vocab.get(word + self.suffix)
        symbols = word[:-1] + chr(_END + ord(word[-1])) if self.suffix else word
        if whole is not None and (len(symbols) == 1 or whole in self.parts):
            return [whole]
        n = len(symbols)
        last: list[tuple[int, int] | None] = [None] * (n + 1)
        fits, known = self._fits, self.fits
        for end, found in self.automaton.iter(symbols):
            token, size = found
            start = end + 1 - size
            if last[end + 1] is not None:
                continue
            if start == 0:
                last[end + 1] = found
            else:
                before = last[start]
                if before is not None and (fits.get(before[0] << 32 | token) or known(before[0], token)):
                    last[end + 1] = found
        ids = []
        while n:
            step = last[n]
            if step is None:
                raise ValueError(f"no token ends at {n} in {word!r}")
            ids.append(step[0])
            n -= step[1]
        return ids[::-1]

    def decode(self, ids: list[int]) -> str:
        """The tokens' strings with a space between them (the vocabulary file names no decoder)."""
        return " ".join(map(self.strings.__getitem__, ids))


def _coder(path: str) -> tuple[PrefixBpe, Segmenter]:
    def load():
        coder, cutter = PrefixBpe(path), Segmenter(path)
        for content, i in cutter.special.items():
            coder.strings[i] = content
        return coder, cutter

    return arrowkit.kept(("coder", path), load)


class WordTable(dict):
    """pre-token -> (ids joined by spaces, decoded string, number of ids), filled by the programme.

    A full table becomes the former one, and a word found there moves over, so
    frequent words stay when rare ones go.
    """

    def __init__(self, path: str):
        super().__init__()
        self.coder, self.cutter = _coder(path)
        self.former: dict[str, tuple[str, str, int]] = {}

    def __missing__(self, word: str) -> tuple[str, str, int]:
        out = self.former.get(word)
        if out is None:
            special = self.cutter.special.get(word)
            ids = [special] if special is not None else self.coder.encode_word(mapped(word))
            out = " ".join(map(str, ids)), self.coder.decode(ids), len(ids)
        if len(self) >= KEPT_WORDS // 2:
            self.former = dict(self)
            self.clear()
        self[word] = out
        return out

    def text(self, text: str) -> tuple[str, str, int]:
        """(decimal ids joined by spaces, decoded text, number of ids) of a whole text."""
        found = [self[w] for w in self.cutter.words(text)]
        if not found:
            return "", "", 0
        ids, strings, counts = zip(*found)
        return " ".join(ids), " ".join(strings), sum(counts)


def word_table(path: str) -> WordTable:
    return arrowkit.kept(("words", path), lambda: WordTable(path))


def encode_texts(docs: DataFrame, path: str, text: str = "text", keep: tuple[str, ...] = ("doc_id",), full: bool = False) -> DataFrame:
    """Encodes and decodes every whole text; a null text counts as empty.

    Returns ``keep``, ``n_tokens``, ``ids_sha256``, ``decoded_sha256`` and, with
    ``full``, the ids (``token_ids``) and the decoded text (``decoded``).  Narrow:
    no shuffle; each row is handled alone, so repeated rows, ties and long texts
    need no care beyond the slices' bounded size.
    """
    names = [*keep]
    source = docs.select(*names, F.col(text).alias("__text"))
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema if f.name in names] + ["n_tokens long", "ids_sha256 string", "decoded_sha256 string"] + (["token_ids array<int>", "decoded string"] if full else []))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = word_table(path)
        sha = hashlib.sha256
        for part in arrowkit.slices(batches, "__text", 4 << 20):
            counts, ids_sha, text_sha, all_ids, all_text = [], [], [], [], []
            for value in part.column("__text").to_pylist():
                ids, decoded, n = table.text(value or "")
                counts.append(n)
                ids_sha.append(sha(ids.encode()).hexdigest())
                text_sha.append(sha(decoded.encode()).hexdigest())
                if full:
                    all_ids.append([int(x) for x in ids.split()])
                    all_text.append(decoded)
            columns = [part.column(c) for c in names] + [pa.array(counts, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())]
            columns += [pa.array(all_ids, pa.list_(pa.int32())), pa.array(all_text, pa.string())] if full else []
            yield pa.RecordBatch.from_arrays(columns, names=[*names, "n_tokens", "ids_sha256", "decoded_sha256"] + (["token_ids", "decoded"] if full else []))

    return source.mapInArrow(arrowkit.tidy(run), schema)


def decode_ids(rows: DataFrame, path: str, ids: str = "token_ids", into: str = "decoded") -> DataFrame:
    """Adds the decoded text of an id list; null lists give null."""
    @F.udf("string", useArrow=True)
    def decoded(values):
        return None if values is None else _coder(path)[0].decode([int(x) for x in values])

    return rows.withColumn(into, decoded(F.col(ids)))
