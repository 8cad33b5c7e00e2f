"""Cutting text into the pre-tokens of the lower-casing word-level BPE vocabulary.

The vocabulary normalises (NFC, lower case), drops white space and encodes each
pre-token alone, so a document's ids are the ids of its pre-tokens in order.
Texts made of ASCII and Latin-1 letters only, for which NFC changes nothing and
the character classes of ``re`` agree with the library's, take a ``re`` path;
every other text goes through the library's own normaliser and pre-tokenizer.
"""

from __future__ import annotations

import re
from functools import lru_cache

from treelogic.llm import arrowkit

# The byte-to-character table of byte-level BPE keeps these printable bytes.
_KEPT_BYTES = [*range(33, 127), *range(161, 173), *range(174, 256)]


@lru_cache(maxsize=1)
def byte_chars() -> list[str]:
    """The character that stands for each byte in a byte-level vocabulary."""
    spare = iter(range(256, 512))
    kept = set(_KEPT_BYTES)
    return [chr(b) if b in kept else chr(next(spare)) for b in range(256)]


def library(path: str):
    """The tokenizers library's object for a vocabulary file (one for each worker)."""
    def load():
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        return Tokenizer.from_file(path)

    return arrowkit.kept(("library", path), load)


class Segmenter:
    """``words(text)``: the pre-tokens of a text as strings of byte characters."""

    _plain = re.compile(r"[\t-\r -~À-ÖØ-öø-ÿ]*")
    _cut = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^\sa-zß-öø-ÿ0-9]+")

    def __init__(self, path: str):
        self.library = library(path)
        added = self.library.get_added_tokens_decoder()
        self.special = {t.content: i for i, t in added.items()}
        self._special = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        #: a character that every added token begins with, if there is one, for a quick look
        firsts = {content[0] for content in self.special}
        self._mark = firsts.pop() if len(firsts) == 1 else ""

    def words(self, text: str) -> list[str]:
        """Raw pre-tokens; those of the ``re`` path are not yet byte characters (see ``mapped``)."""
        if self._special and self._mark in text and self._special.search(text):
            out: list[str] = []
            for i, part in enumerate(self._special.split(text)):
                out += [part] if i % 2 else self.words(part)
            return out
        if self._plain.fullmatch(text):
            return self._cut.findall(text.lower())
        normal = self.library.normalizer.normalize_str(text)
        # \0 marks what is already in byte characters: it cannot occur in them
        return ["\0" + w for w, _ in self.library.pre_tokenizer.pre_tokenize_str(normal)]


def mapped(word: str) -> str:
    """A pre-token in byte characters."""
    if word[0] == "\0":
        return word[1:]
    if word.isascii():
        return word
    table = byte_chars()
    return "".join([table[b] for b in word.encode()])
