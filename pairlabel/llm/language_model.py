"""Language-model scores by deleted interpolation of unigram and bigram estimates.

P(w | h) = a2[b] * c(h, w) / c(h) + a1[b] * c(w) / N + a0[b] / (V + 1), where b is a
bucket of the context's frequency. The weights a are learned by expectation
maximisation on deleted counts: each training token is predicted from all other
training tokens, its own occurrence taken out of every count. Tokens whose two
deleted estimates lie within the same eighths of a power of two enter the
maximisation together, by the means of their estimates, so what the driver gets has
a fixed bound; within a step of that size the estimates differ from their mean by at
most 4.5 %, whose square bounds the error of a token's share.

Counts come from all training documents. Texts are dealt into blocks of bounded
size. A block asks for the counts of its distinct n-grams: sorted 64-bit keys, cut
into ranges, each with the block's own training counts. What has been asked of
one range is summed in one place and answered to each block, which then knows for
each token c(w) and c(h, w). These are kept per document in the shared folder; the
weights and the scores follow from them without another shuffle. A frequent word
is one key per block, however often it occurs.

Defined results: null and empty texts have the end token alone; a row with a null
id is a training row (crc32 of the empty text); repeated rows count as often as
they occur; without training rows scores are those of the uniform part; an empty
table gives an empty result; columns other than the two named ones play no part.
Words are told apart by 62-bit hashes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize
from .shingles import mix, text_slices, word_hashes

_U = np.uint64
_END = _U(0x2545F4914F6CDD1D)
_START = _U(0x8E9D5A3C71B46F27)
BUCKETS = 20  # by powers of two of the context's count; 0: unseen
GRAIN = 8  # steps per power of two by which deleted estimates are gathered; within a step their means are exact


def token_keys(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Unigram keys, bigram keys and offsets of the documents' tokens (words, then one end each). Bit 1 of a key tells the two kinds apart, bit 0 is free."""
    uni, sizes = [], []
    for _, raw, offsets in text_slices(column):
        words, at = word_hashes(raw, offsets)
        ends = at[1:] + np.arange(len(at) - 1)
        out = np.empty(len(words) + len(at) - 1, _U)
        is_end = np.zeros(len(out), dtype=bool)
        is_end[ends] = True
        out[is_end], out[~is_end] = _END, words
        uni.append(out)
        sizes.append(np.diff(at) + 1)
    tokens = np.concatenate([*uni, np.zeros(0, _U)])
    offsets = np.concatenate([[0], np.cumsum(np.concatenate([*sizes, np.zeros(0, np.int64)]))]).astype(np.int64)
    context = np.empty_like(tokens)
    context[1:] = tokens[:-1]
    context[offsets[:-1]] = _START
    with np.errstate(over="ignore"):
        pair = mix(context * _U(0x9E3779B97F4A7C15) + mix(tokens))
    low = ~_U(3)
    return mix(tokens) & low | _U(2), pair & low, offsets


def _squeeze(sorted_keys: np.ndarray) -> bytes:
    """Differences in as few whole bytes as the greatest needs."""
    steps = np.diff(sorted_keys, prepend=_U(0))
    width = max(1, -(-int(steps[1:].max() if len(steps) > 1 else 0).bit_length() // 8))
    head = sorted_keys[:1].astype("<u8").tobytes()
    return bytes([width]) + head + steps[1:].astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].tobytes()


def _unsqueeze(data: bytes) -> np.ndarray:
    width, raw = data[0], np.frombuffer(data, np.uint8, offset=9)
    steps = np.zeros((len(raw) // width + 1, 8), np.uint8)
    steps[0] = np.frombuffer(data, np.uint8, count=8, offset=1)
    steps[1:, :width] = raw.reshape(-1, width)
    return np.cumsum(steps.reshape(-1).view("<u8"), dtype=_U)


def _small(counts: np.ndarray) -> bytes:
    """Counts as bytes, with those over 254 behind them."""
    big = np.nonzero(counts > 254)[0]
    head = np.array([len(counts), len(big)], "<i8").tobytes()
    return head + np.minimum(counts, 255).astype(np.uint8).tobytes() + big.astype("<i8").tobytes() + counts[big].astype("<i8").tobytes()


def _unsmall(data: bytes) -> np.ndarray:
    n, m = np.frombuffer(data, "<i8", count=2).tolist()
    out = np.frombuffer(data, np.uint8, count=n, offset=16).astype(np.int64)
    out[np.frombuffer(data, "<i8", count=m, offset=16 + n)] = np.frombuffer(data, "<i8", count=m, offset=16 + n + 8 * m)
    return out


def _planes(counts: np.ndarray) -> bytes:
    """Counts by significance of their bytes, which compresses well."""
    width = max(1, -(-int(counts.max() if len(counts) else 0).bit_length() // 8))
    return bytes([width]) + counts.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T.tobytes()


def _unplanes(data: bytes) -> np.ndarray:
    width, raw = data[0], np.frombuffer(data, np.uint8, offset=1)
    out = np.zeros((len(raw) // width, 8), np.uint8)
    out[:, :width] = raw.reshape(width, -1).T
    return out.reshape(-1).view("<u8").astype(np.int64)


def _summed(keys: np.ndarray, train: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys, sorted, and how many of each are in training documents."""
    all_ = np.sort(keys | train.astype(_U))
    plain = all_ & ~_U(1)
    first = np.nonzero(np.concatenate([[True], plain[1:] != plain[:-1]]))[0] if len(plain) else np.zeros(0, np.int64)
    counts = np.add.reduceat((all_ & _U(1)).astype(np.int64), first) if len(first) else np.zeros(0, np.int64)
    return plain[first], counts


def _by_block(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, pa.Table]]:
    """Rows sorted by block, block by block."""
    held: list[pa.RecordBatch] = []
    at = None
    for b in batches:
        block = b.column("block").to_numpy(zero_copy_only=False)
        cuts = [0, *(np.nonzero(np.diff(block))[0] + 1).tolist(), len(block)]
        for s, e in zip(cuts, cuts[1:], strict=False):
            if e > s:
                if at is not None and block[s] != at:
                    yield at, pa.Table.from_batches(held)
                    held = []
                at = int(block[s])
                held.append(b.slice(s, e - s))
    if held:
        yield at, pa.Table.from_batches(held)


def _packed(batch: pa.RecordBatch) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_batch(batch)
    return sink.getvalue().to_pybytes()


def _unpacked(parcels: pa.Table) -> pa.Table:
    return pa.concat_tables([pa.ipc.open_stream(pa.py_buffer(x)).read_all() for x in parcels.column("texts").to_pylist()])


_KEPT = "doc_id long, held_out boolean, n_tokens long, n_known long, types long, c_w binary, c_hw binary"


def token_counts(docs: DataFrame, held_out, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = 1 << 23) -> DataFrame:
    """Per document the training counts of its tokens and bigrams; further rows (null n_tokens) hold the numbers of distinct training tokens."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"), held_out.alias("held_out"))
    size, n_rows = rows.agg(F.coalesce(F.sum(F.octet_length("text").cast("long")), F.lit(0)), F.count(F.lit(1))).first()
    n_blocks = max(1, (size + 64 * n_rows) // block_bytes)
    bits = max(0, int(np.ceil(np.log2(max(1, size // 4 // (1 << 21))))))
    parts = max(1, min(n_blocks, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")) if n_blocks < 1000 else n_blocks // 2))
    block = F.pmod(F.xxhash64("doc_id", F.octet_length("text"), F.substring("text", 1, 64)), F.lit(n_blocks))

    def parcel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The texts of one block that a batch holds, compressed together: less to shuffle."""
        for b in batches:
            at = b.column("block").to_numpy(zero_copy_only=False)
            order = np.argsort(at, kind="stable")
            cuts = [0, *(np.nonzero(np.diff(at[order]))[0] + 1).tolist(), len(at)]
            own = b.select(["doc_id", "held_out", "text"])
            spans = [order[s:e] for s, e in zip(cuts, cuts[1:], strict=False) if e > s]
            yield pa.RecordBatch.from_arrays([pa.array([int(at[o[0]]) for o in spans], pa.int64()), pa.array([_packed(own.take(pa.array(o))) for o in spans], pa.binary())], ["block", "texts"])

    dealt = rows.withColumn("block", block).mapInArrow(parcel, "block long, texts binary").repartition(parts, "block")

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for at, parcels in _by_block(batches):
            table = _unpacked(parcels)
            uni, pair, offsets = token_keys(table.column("text").combine_chunks())
            train = np.repeat(~table.column("held_out").to_numpy(), np.diff(offsets))
            keys, counts = _summed(np.concatenate([uni, pair]), np.concatenate([train, train]))
            part = (keys >> _U(64 - bits)).astype(np.int64) if bits else np.zeros(len(keys), np.int64)
            cuts = [0, *(np.nonzero(np.diff(part))[0] + 1).tolist(), len(keys)]
            spans = [(s, e) for s, e in zip(cuts, cuts[1:], strict=False) if e > s]
            cols = [
                pa.array([int(part[s]) for s, _ in spans], pa.int64()),
                pa.array([at] * len(spans), pa.int64()),
                pa.array([_squeeze(keys[s:e]) for s, e in spans], pa.binary()),
                pa.array([_small(counts[s:e]) for s, e in spans], pa.binary()),
            ]
            yield pa.RecordBatch.from_arrays(cols, ["span", "block", "keys", "counts"])

    def answer(table: pa.Table) -> pa.Table:
        keys = [_unsqueeze(x) for x in table.column("keys").to_pylist()]
        lengths = [len(k) for k in keys]
        all_ = np.concatenate(keys)
        del keys
        counts = np.concatenate([_unsmall(x) for x in table.column("counts").to_pylist()])
        order = np.argsort(all_, kind="stable")
        ordered = all_[order]
        first = np.nonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]]))[0]
        sums = np.add.reduceat(counts[order], first)
        types = int(((sums > 0) & ((ordered[first] & _U(2)) > 0)).sum())
        total = np.empty(len(all_), np.int64)
        total[order] = np.repeat(sums, np.diff(np.append(first, len(all_))))
        parts_ = np.split(total, np.cumsum(lengths)[:-1])
        span = table.column("span").to_pylist()
        return pa.table({
            "block": pa.array([*table.column("block").to_pylist(), -1 - span[0]], pa.int64()),
            "span": pa.array([*span, span[0]], pa.int64()),
            "types": pa.array([None] * len(span) + [types], pa.int64()),
            "totals": pa.array([*map(_small, parts_), None], pa.binary()),
        })

    asked = dealt.sortWithinPartitions("block").mapInArrow(ask, "span long, block long, keys binary, counts binary")
    answers = asked.groupBy("span").applyInArrow(answer, "block long, span long, types long, totals binary").repartition(parts, "block")

    def kept(texts: pa.Table, got: pa.Table) -> pa.Table:
        names = ["doc_id", "held_out", "n_tokens", "n_known", "types", "c_w", "c_hw"]
        kinds = [pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary()]
        if not texts.num_rows:
            n = got.num_rows
            return pa.table([pa.nulls(n, k) if c != "types" else got.column("types").combine_chunks() for c, k in zip(names, kinds, strict=True)], names=names)
        texts = _unpacked(texts)
        uni, pair, offsets = token_keys(texts.column("text").combine_chunks())
        keys, _ = _summed(np.concatenate([uni, pair]), np.zeros(2 * len(uni), dtype=bool))
        order = np.argsort(got.column("span").to_numpy())
        blobs = got.column("totals").to_pylist()
        totals = np.concatenate([_unsmall(blobs[k]) for k in order.tolist()])
        c_w, c_hw = totals[np.searchsorted(keys, uni)], totals[np.searchsorted(keys, pair)]
        spans = list(zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True))
        known = np.add.reduceat((c_w > 0).astype(np.int64), offsets[:-1])
        cols = [texts.column("doc_id"), texts.column("held_out"), np.diff(offsets), known, pa.nulls(len(spans), pa.int64()), [_planes(c_w[s:e]) for s, e in spans], [_planes(c_hw[s:e]) for s, e in spans]]
        return pa.table([c if isinstance(c, (pa.ChunkedArray, pa.Array)) else pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=names)

    met = dealt.groupBy("block").cogroup(answers.groupBy("block"))
    return materialize(met.applyInArrow(kept, _KEPT), "token-counts")


def bucket_of(context: np.ndarray) -> np.ndarray:
    return np.minimum(BUCKETS - 1, np.where(context > 0, np.floor(np.log2(np.maximum(context, 1))).astype(np.int64) + 1, 0))


def _estimates(c_hw: np.ndarray, c_h: np.ndarray, c_w: np.ndarray, n: float, deleted: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bucket, bigram and unigram estimates; deleted: each token without its own occurrence."""
    less = 1 if deleted else 0
    c_h = c_h - less
    p2 = np.where(c_h > 0, (c_hw - less) / np.maximum(c_h, 1), 0.0)
    return bucket_of(c_h), p2, (c_w - less) / max(1.0, n - less)


def learn_weights(cells: list[tuple[int, float, float, float]], uniform: float, rounds: int = 60) -> np.ndarray:
    """Weights (bigram, unigram, uniform) by bucket, by expectation maximisation on (bucket, p2, p1, count)."""
    weights = np.tile([0.3, 0.6, 0.1], (BUCKETS, 1))
    weights[0] = [0.0, 0.9, 0.1]
    if not cells:
        return weights
    b, p2, p1, n = (np.array(x) for x in zip(*cells, strict=True))
    b = b.astype(int)
    parts = np.column_stack([p2, p1, np.full(len(b), uniform)])
    for _ in range(rounds):
        share = weights[b] * parts
        share *= (n / np.maximum(share.sum(axis=1), 1e-300))[:, None]
        new = np.column_stack([np.bincount(b, share[:, k], minlength=BUCKETS) for k in range(3)])
        seen = new.sum(axis=1) > 0
        weights[seen] = new[seen] / new[seen].sum(axis=1, keepdims=True)
    weights[:, 2] = np.maximum(weights[:, 2], 1e-6)  # no token is impossible
    weights[0, 0] = 0.0
    return weights / weights.sum(axis=1, keepdims=True)


def _arrays(c_w: bytes, c_hw: bytes, n_docs: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    own = _unplanes(c_w)
    return _unplanes(c_hw), np.concatenate([[n_docs], own[:-1]]), own  # the start occurs once in each training document


def _each(b: pa.RecordBatch) -> Iterator[tuple[bytes, bytes]]:
    for x, y in zip(b.column("c_w"), b.column("c_hw"), strict=True):
        yield x.as_py(), y.as_py()


def interpolated_scores(docs: DataFrame, held_out=None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of each row.

    held_out: a boolean column; by default the rows whose crc32 of the id as text leaves 2 modulo 7.
    """
    if held_out is None:
        held_out = F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit(""))) % 7 == 2
    counts = token_counts(docs, held_out, id_col, text_col)
    n, v, n_docs = counts.agg(
        F.coalesce(F.sum(F.when(~F.col("held_out"), F.col("n_tokens"))), F.lit(0)), F.coalesce(F.sum("types"), F.lit(0)), F.count_if(~F.col("held_out"))
    ).first()
    rows = counts.where(F.col("n_tokens").isNotNull())

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top = 64 * GRAIN
        found: dict[int, np.ndarray] = {}
        for b in batches:
            codes, held = [], 0

            def count(codes: list[tuple]) -> None:
                cells, two, one = (np.concatenate(x) for x in zip(*codes, strict=True))
                cell, where = np.unique(cells, return_inverse=True)
                sums = np.column_stack([np.bincount(where), np.bincount(where, two), np.bincount(where, one)])
                for c, s in zip(cell.tolist(), sums, strict=True):
                    found[c] = found[c] + s if c in found else s
                codes.clear()

            for c_w, c_hw in _each(b):
                bucket, p2, p1 = _estimates(*_arrays(c_w, c_hw, n_docs), n, True)
                q2 = np.where(p2 > 0, np.clip(np.round(-np.log2(np.where(p2 > 0, p2, 1)) * GRAIN), 0, top - 2), top - 1).astype(np.int64)
                q1 = np.where(p1 > 0, np.clip(np.round(-np.log2(np.where(p1 > 0, p1, 1)) * GRAIN), 0, top - 2), top - 1).astype(np.int64)
                codes.append(((bucket * top + q2) * top + q1, p2, p1))
                held += len(q1)
                if held > 1 << 20:
                    count(codes)
                    held = 0
            if codes:
                count(codes)
        sums = np.array(list(found.values())).reshape(-1, 3)
        yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.int64()), *[pa.array(sums[:, k], pa.float64()) for k in range(3)]], ["cell", "n", "two", "one"])

    # a fixed grid, so what comes back has a fixed bound
    cells = rows.where(~F.col("held_out")).select("c_w", "c_hw").mapInArrow(gather, "cell long, n double, two double, one double")
    grid = cells.groupBy("cell").agg(F.sum("n").alias("n"), F.sum("two").alias("two"), F.sum("one").alias("one")).collect()
    top = 64 * GRAIN
    weights = learn_weights([(r["cell"] // top // top, r["two"] / r["n"], r["one"] / r["n"], r["n"]) for r in grid], 1 / (v + 1))

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base_of = np.log10(float(n + v + 1))
        for b in batches:
            base, full = [], []
            for one, two in _each(b):
                c_hw, c_h, c_w = _arrays(one, two, n_docs)
                bucket, p2, p1 = _estimates(c_hw, c_h, c_w, n, False)
                w = weights[bucket]
                full.append(float(np.log10(w[:, 0] * p2 + w[:, 1] * p1 + w[:, 2] / (v + 1)).sum()))
                base.append(float((np.log10(c_w + 1.0) - base_of).sum()))
            cols = [b.column(c) for c in ("doc_id", "held_out", "n_tokens", "n_known")]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(base, pa.float64()), pa.array(full, pa.float64())], ["doc_id", "held_out", "n_tokens", "n_known", "base_score", "score"])

    out = rows.select("doc_id", "held_out", "n_tokens", "n_known", "c_w", "c_hw").mapInArrow(score, "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    return out.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(n).cast("long").alias("train_tokens"), "base_score", "score")
