"""Token ids of a tokenizer file of the tokenizers library, faster by a bounded cache of words.

The library splits a text into words before it merges anything, and a word's ids
do not depend on its neighbours. For the two kinds of file whose splitting is
known (byte-level, and lower-cased words with word ends) the words of a text are
found with an equal pattern, the library encodes each new word, and a cache keeps
its ids. Texts with characters on which the patterns or the case mapping could
differ, and texts that hold a special token's string, go to the library whole.
"""

from __future__ import annotations

import json
import re
import struct
from functools import lru_cache

import numpy as np
from tokenizers import Tokenizer

#: The patterns by which the two kinds of file split text.
BYTE_LEVEL = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
WORD_ENDS = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: Characters on which the libraries surely agree: printable ASCII, its usual white space, Latin letters up to U+017F but the dotted I, the long s and soft hyphen, and common punctuation.
#: On such texts these give the same words as the two patterns, faster.
_LETTER, _DIGIT = "a-zA-ZªµºÀ-ÖØ-öø-ž", "0-9²³¹¼-¾"
_SURE_BYTE_LEVEL = re.compile(rf"'(?:s|t|re|ve|m|ll|d)| ?[{_LETTER}]+| ?[{_DIGIT}]+| ?[^\s{_LETTER}{_DIGIT}]+|\s+(?!\S)|\s+")
_SURE_WORD_ENDS = re.compile(rf"'(?:s|t|re|ve|m|ll|d)|[{_LETTER}]+|[{_DIGIT}]|[^\s{_LETTER}{_DIGIT}]+")
_UNSURE = re.compile(r"[^\n\t\r\x20-\x7E¡-¬®-įı-ž–—‘-„…]")


def byte_alphabet() -> dict[str, int]:
    """The printable stand-ins that byte-level vocabularies use for bytes, by rule: printable Latin-1 stands for itself, the others follow from U+0100."""
    own = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + k): b for k, b in enumerate(rest)}


class _Cache(dict):
    """Word to ids as little-endian unsigned 32-bit integers; a new word is encoded by the library's model."""

    def __init__(self, model, most: int):
        super().__init__()
        self.tokenize, self.most = model.tokenize, most
        self.bytes_as = {b: c for c, b in byte_alphabet().items()}

    def __missing__(self, word: str) -> bytes:
        as_model = word.translate(self.bytes_as) if word.isascii() else word.encode().decode("latin-1").translate(self.bytes_as)
        ids = [t.id for t in self.tokenize(as_model)]
        made = struct.pack(f"<{len(ids)}I", *ids)
        if len(self) < self.most:
            self[word] = made
        return made


class WordEncoder:
    """encode(text) gives the ids as little-endian unsigned 32-bit integers."""

    def __init__(self, path: str, max_words: int = 250_000):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.cache = _Cache(self.library.model, max_words)
        self.vocab_size = self.library.get_vocab_size(with_added_tokens=True)
        special = [re.escape(t["content"]) for t in spec.get("added_tokens") or []]
        self.special = re.compile("|".join(special)) if special else None
        pre, norm = spec.get("pre_tokenizer") or {}, spec.get("normalizer")
        self.pattern = self.lower = None
        if pre.get("type") == "ByteLevel" and pre.get("use_regex") and not pre.get("add_prefix_space") and norm is None:
            self.pattern, self.lower = _SURE_BYTE_LEVEL, False
        elif pre.get("type") == "Sequence" and [p.get("type") for p in pre["pretokenizers"]] == ["Split", "ByteLevel"] and (
            pre["pretokenizers"][0]["pattern"].get("Regex") == WORD_ENDS and [n.get("type") for n in (norm or {}).get("normalizers", [])] == ["NFC", "Replace", "Lowercase"]
        ):
            self.pattern, self.lower = _SURE_WORD_ENDS, True

    def whole(self, text: str) -> bytes:
        return np.array(self.library.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def encode(self, text: str) -> bytes:
        if self.pattern is None or (self.special and self.special.search(text)) or _UNSURE.search(text):
            return self.whole(text)
        words = self.pattern.findall(text.lower() if self.lower else text)
        return b"".join(map(self.cache.__getitem__, words))

    def release(self) -> None:
        """Frees the cache; workers outlive their tasks."""
        self.cache.clear()


@lru_cache(maxsize=4)
def encoder(path: str) -> WordEncoder:
    """One encoder for each file and worker."""
    return WordEncoder(path)
