"""Byte-pair encoding as a streaming transducer with bounded lookahead, and decoding as an incremental state machine.

The merge list alone tells how far to the right a merge can be disturbed. The
merge (u, v) fails to happen where some end piece of v (v itself or a right part
in its derivation) is taken by an earlier merge (that piece, x); whether that one
happens depends in turn on the right end of x. Following such chains gives for
each merge the number of bytes behind it that can matter: the length of the next
merge's right part plus that merge's own reach. The greatest over all merges is
the sufficient lookahead: once so many bytes behind a token's end are known, or the
word has ended there, the token can't change and is emitted. Every word goes
through this transducer, which holds at most a window of bytes; a bounded cache
keeps what it has emitted for a word.

Decoding maps ids to bytes and feeds them to an incremental UTF-8 decoder that
replaces what is invalid.

Defined results: null and empty texts give no ids and the empty text; a special
token's string within a text gives its id; an unknown id raises KeyError; columns
other than the two named ones play no part; an empty table gives an empty result.
"""

from __future__ import annotations

import codecs
import hashlib
import heapq
import json
import re
import struct
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tokens import BYTE_LEVEL, byte_alphabet


class Transducer:
    """Encoder and decoder of a byte-level tokenizer file."""

    def __init__(self, path: str, window: int = 4096, max_words: int = 300_000):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, pre = spec["model"], spec.get("pre_tokenizer") or {}
        if model["type"] != "BPE" or pre.get("type") != "ByteLevel" or not pre.get("use_regex") or pre.get("add_prefix_space") or spec.get("normalizer"):
            raise ValueError("a byte-level BPE file without a normalizer is needed")
        alphabet = byte_alphabet()
        to_bytes = lambda s: bytes(alphabet[c] for c in s)
        vocab = model["vocab"]
        self.bytes_of = {i: to_bytes(s) for s, i in vocab.items()}
        pairs = [tuple(m.split(" ", 1)) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        self.merges = [(vocab[a], vocab[b], vocab[a + b]) for a, b in pairs]
        self.rank = {(a, b): (k, c) for k, (a, b, c) in reversed(list(enumerate(self.merges)))}
        self.first_rank = {p: k for p, (k, _) in self.rank.items()}
        self.single = [0] * 256
        for s, i in vocab.items():
            if len(s) == 1:
                self.single[alphabet[s]] = i
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens") or []}
        self.special_at = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.bytes_of |= {i: s.encode() for s, i in self.special.items()}
        self.words = regex.compile(BYTE_LEVEL)
        self.lookahead = self._lookahead()
        self.window = max(window, 2 * self.lookahead)
        self.max_words = max_words
        self.cache: dict[str, bytes] = {}

    def _lookahead(self) -> int:
        parts = {c: (a, b) for a, b, c in reversed(self.merges)}
        size = {i: len(b) for i, b in self.bytes_of.items()}
        reach: dict[int, int] = {}  # by left part: how far the merges seen so far that begin with it can look
        most = 0
        for a, b, _ in self.merges:
            far, end = 0, b
            while True:
                far = max(far, reach.get(end, 0))
                if end not in parts:
                    break
                end = parts[end][1]
            own = size[b] + far
            reach[a] = max(reach.get(a, 0), own)
            most = max(most, own)
        return most

    def merge(self, data: bytes) -> list[int]:
        """Ids of a word, all at once."""
        ids: list[int | None] = [self.single[x] for x in data]
        n = len(ids)
        if n < 2:
            return ids
        if n <= 64:
            get, none = self.first_rank.get, len(self.merges)
            ranks = [get(p, none) for p in zip(ids, ids[1:], strict=False)]
            while ranks and (best := min(ranks)) < none:
                k = ranks.index(best)
                ids[k] = made = self.merges[best][2]
                del ids[k + 1], ranks[k]
                if k:
                    ranks[k - 1] = get((ids[k - 1], made), none)
                if k < len(ranks):
                    ranks[k] = get((made, ids[k + 1]), none)
            return ids
        rank = self.rank
        after, before = [*range(1, n), -1], [-1, *range(n - 1)]
        heap = [(rank[p][0], k, p) for k, p in enumerate(zip(ids, ids[1:], strict=False)) if p in rank]
        heapq.heapify(heap)
        while heap:
            _, k, p = heapq.heappop(heap)
            j = after[k]
            if j < 0 or ids[k] is None or (ids[k], ids[j]) != p:
                continue
            ids[k], ids[j] = rank[p][1], None
            after[k] = after[j]
            if after[j] >= 0:
                before[after[j]] = k
                q = ids[k], ids[after[j]]
                if q in rank:
                    heapq.heappush(heap, (rank[q][0], k, q))
            if before[k] >= 0:
                q = ids[before[k]], ids[k]
                if q in rank:
                    heapq.heappush(heap, (rank[q][0], before[k], q))
        return [i for i in ids if i is not None]

    def stream(self, chunks: Iterable[bytes]) -> Iterator[int]:
        """Ids of one word that comes in chunks, each emitted once it is stable; holds at most a window. The end of the chunks is the end of the word, where the rest is stable."""
        held = b""
        for chunk in chunks:
            for s in range(0, len(chunk), self.window):
                held += chunk[s : s + self.window]
                while len(held) >= self.window:
                    done, limit = 0, len(held) - self.lookahead
                    for i in self.merge(held):
                        end = done + len(self.bytes_of[i])
                        if end > limit:
                            break
                        yield i
                        done = end
                    if not done:
                        break
                    held = held[done:]
        yield from self.merge(held)

    def _word(self, word: str) -> bytes:
        data = word.encode("utf-8", "surrogatepass")
        ids = list(self.stream(data[s : s + self.window] for s in range(0, len(data), self.window)))
        return _packer(len(ids)).pack(*ids)

    def encode_parts(self, text: str, part: int = 1 << 16) -> Iterator[bytes]:
        """The ids as little-endian unsigned 32-bit integers, part by part; the parts end where a word surely ends."""
        for k, plain in enumerate(self.special_at.split(text) if self.special_at else [text]):
            if k % 2:
                yield np.array([self.special[plain]], dtype="<u4").tobytes()
                continue
            words: list[str] = []
            for m in self._slices(plain, part):
                words = self.words.findall(m)
                yield self._encode_words(words)

    @staticmethod
    def _slices(text: str, part: int) -> Iterator[str]:
        """Cuts before a single space between two other characters: no word of the pattern crosses that."""
        at = 0
        while len(text) - at > part:
            m = _BREAK.search(text, at + part)
            if not m:
                break
            yield text[at : m.start() + 1]
            at = m.start() + 1
        yield text[at:]

    def _encode_words(self, words: list[str]) -> bytes:
        cache = self.cache
        try:
            return b"".join(map(cache.__getitem__, words))
        except KeyError:
            pass
        if len(cache) > self.max_words:
            cache.clear()
        long: dict[str, bytes] = {}
        for w in dict.fromkeys(words):
            if w not in cache:
                (cache if len(w) <= 64 else long)[w] = self._word(w)
        return b"".join([cache[w] if w in cache else long[w] for w in words])

    def encode(self, text: str) -> np.ndarray:
        return np.frombuffer(b"".join(self.encode_parts(text)), dtype="<u4")

    def decode_parts(self, parts: Iterable[np.ndarray]) -> Iterator[str]:
        machine, table = codecs.getincrementaldecoder("utf-8")("replace"), self.bytes_of
        for ids in parts:
            yield machine.decode(b"".join([table[i] for i in ids.tolist()]))
        yield machine.decode(b"", final=True)

    def decode(self, ids: np.ndarray) -> str:
        return "".join(self.decode_parts([ids]))


@lru_cache(maxsize=256)
def _packer(n: int) -> struct.Struct:
    return struct.Struct(f"<{n}I")


_BREAK = regex.compile(r"[^\s](?= [^\s])")


@lru_cache(maxsize=2)
def transducer(path: str) -> Transducer:
    """One for each file and worker."""
    return Transducer(path)


def encode_documents(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids (array of int) for each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = transducer(tokenizer)
        for b in batches:
            ids = [t.encode(x.as_py() or "").astype(np.int32) for x in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])

    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t"))
    return rows.mapInArrow(run, "doc_id long, ids array<int>")


def decode_documents(encoded: DataFrame, tokenizer: str) -> DataFrame:
    """doc_id, text for each row of doc_id, ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = transducer(tokenizer)
        for b in batches:
            texts = [t.decode(np.array(x.as_py() or [], dtype="<u4")) for x in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def round_trip(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: each document is encoded and decoded part by part, in constant memory beyond its text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = transducer(tokenizer)
        for b in batches:
            rows = []
            for x in b.column(1):
                of_ids, of_text, n = hashlib.sha256(), hashlib.sha256(), 0

                def seen(text: str, of_ids=of_ids) -> Iterator[np.ndarray]:
                    nonlocal n
                    for part in t.encode_parts(text):
                        of_ids.update(part)
                        n += len(part) // 4
                        yield np.frombuffer(part, "<u4")

                for text in t.decode_parts(seen(x.as_py() or "")):
                    of_text.update(text.encode())
                rows.append((n, of_ids.hexdigest(), of_text.hexdigest()))
            cols = list(zip(*rows, strict=True)) or [(), (), ()]
            arrays = [b.column(0), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.string()), pa.array(cols[2], pa.string())]
            yield pa.RecordBatch.from_arrays(arrays, ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t"))
    return rows.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
