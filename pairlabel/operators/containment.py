"""Passages in documents: shared tokens and the longest common run of every pair that shares a token.

Both texts are taken whole and no token is left out, however common. Documents
are read once for each block of passages. In a task all positions of a slice of
documents are followed together: those that continue a run of some passage stay,
so the work falls with the length of the run and no table of pairs times
positions is made. A block of passages has at most ``block_tokens`` tokens
unless one passage alone has more, so what a task gets has a bounded size.

Defined results: null and empty texts meet nothing; each row of passages is
paired with each row of documents, also where ids repeat or are null; an empty
table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import similarity as S

SLICE_TOKENS, SLICE_CELLS = 1 << 18, 1 << 21


class Passages:
    """A block of passages, coded: one number per distinct token."""

    def __init__(self, ids: list, texts: list[list[str]]) -> None:
        self.ids = ids
        self.vocabulary = sorted({t for text in texts for t in text})
        code = {t: k for k, t in enumerate(self.vocabulary)}
        self.tokens = np.array([code[t] for text in texts for t in text], np.int64)
        sizes = np.array([len(text) for text in texts], np.int64)
        self.item = np.repeat(np.arange(len(texts)), sizes)
        self.end = np.repeat(np.cumsum(sizes), sizes)
        self.distinct = np.array([len(set(text)) for text in texts], np.int64)

    def meet(self, tokens: np.ndarray, doc: np.ndarray, end: np.ndarray, n_docs: int) -> tuple[np.ndarray, ...]:
        """doc, item, shared tokens and longest run, of the pairs that share a token. tokens: -1 where no passage has it; end: where the document of a position ends."""
        n, v = len(self.ids), len(self.vocabulary)
        best = np.zeros(n_docs * n, np.int32)
        at, here = np.arange(len(self.tokens)), np.flatnonzero(tokens >= 0)
        gram_p, gram_d, run = self.tokens, tokens[here], 1
        shared = best
        while len(here):
            held = np.unique(gram_p * n + self.item[at])  # gram, item
            found = np.unique(doc[here] * (v + len(at)) + gram_d)
            found_doc, found_gram = np.divmod(found, v + len(at))
            low, high = np.searchsorted(held, found_gram * n), np.searchsorted(held, (found_gram + 1) * n)
            many = high - low
            item = held[np.repeat(low - np.cumsum(many) + many, many) + np.arange(many.sum())] % n
            cell = np.repeat(found_doc, many) * n + item
            if run == 1:
                shared = np.bincount(cell, minlength=n_docs * n)
            best[cell] = run
            # runs longer by one: of those that both sides have and that do not end here
            stay = np.isin(gram_p, found_gram) & (at + run < self.end[at])
            at, gram_p = at[stay], gram_p[stay]
            go = here + run < end[here]
            here, gram_d = here[go], gram_d[go]
            key_p, next_d = gram_p * v + self.tokens[at + run], tokens[here + run]
            here, gram_d, next_d = here[next_d >= 0], gram_d[next_d >= 0], next_d[next_d >= 0]
            keys, gram_p = np.unique(key_p, return_inverse=True)
            if not len(keys):
                break
            key_d = gram_d * v + next_d
            gram_d = np.minimum(np.searchsorted(keys, key_d), len(keys) - 1)
            same = keys[gram_d] == key_d
            here, gram_d, run = here[same], gram_d[same], run + 1
        met = np.flatnonzero(shared)
        return met // n, met % n, shared[met], best[met]


def _slices(sizes: np.ndarray, n_items: int) -> Iterator[tuple[int, int]]:
    """Ranges of documents of about SLICE_TOKENS tokens, or one document."""
    start, held, most = 0, 0, max(1, SLICE_CELLS // max(1, n_items))
    for k, size in enumerate(sizes):
        if k > start and (held + size > SLICE_TOKENS or k - start >= most):
            yield start, k
            start, held = k, 0
        held += size
    if len(sizes) > start:
        yield start, len(sizes)


def _with_block(documents: DataFrame, ids: list, texts: list[list[str]], schema: str, item_type: pa.DataType) -> DataFrame:
    sent = documents.sparkSession.sparkContext.broadcast((ids, texts))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = Passages(*sent.value)
        names, items = pa.array(block.vocabulary, pa.string()), pa.array(block.ids, item_type)
        for batch in batches:
            lists = batch.column("t")
            sizes = lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            bounds = np.concatenate([[0], np.cumsum(sizes)])
            flat = lists.flatten()
            for a, b in _slices(sizes, len(block.ids)):
                words = flat.slice(bounds[a], bounds[b] - bounds[a])
                codes = pc.fill_null(pc.index_in(words, value_set=names), -1).to_numpy(zero_copy_only=False).astype(np.int64)
                own = sizes[a:b]
                doc, item, shared, longest = block.meet(codes, np.repeat(np.arange(b - a), own), np.repeat(np.cumsum(own), own), b - a)
                if len(doc):
                    columns = [items.take(pa.array(item)), batch.column("doc_id").take(pa.array(doc + a)), pa.array(shared.astype(np.int64)), pa.array(block.distinct[item]), pa.array(longest)]
                    yield pa.RecordBatch.from_arrays(columns, ["item_id", "doc_id", "shared", "size", "run"])

    return documents.mapInArrow(run, schema)


def contained(passages: DataFrame, documents: DataFrame, block_tokens: int = 100_000) -> DataFrame:
    """item_id, doc_id, contained (share of the passage's distinct tokens), run (tokens), for every pair that shares a token."""
    from pyspark.sql.pandas.types import to_arrow_type

    a = passages.select("item_id", S.tokens(F.col("text")).alias("t")).where(F.size("t") > 0)
    b = documents.select("doc_id", S.tokens(F.col("text")).alias("t"))
    item_type, doc_type = a.schema["item_id"].dataType, b.schema["doc_id"].dataType
    schema = f"item_id {item_type.simpleString()}, doc_id {doc_type.simpleString()}, shared long, size long, run int"
    out, ids, texts, held = None, [], [], 0

    def add() -> DataFrame:
        one = _with_block(b, ids, texts, schema, to_arrow_type(item_type))
        return one if out is None else out.unionAll(one)

    for r in a.toLocalIterator():
        if ids and held + len(r["t"]) > block_tokens:
            out, ids, texts, held = add(), [], [], 0
        ids.append(r["item_id"])
        texts.append(r["t"])
        held += len(r["t"])
    if ids or out is None:
        out = add()
    return out.select("item_id", "doc_id", F.round(F.col("shared") / F.col("size"), 6).alias("contained"), "run")
