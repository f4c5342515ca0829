"""Token ids in a binary format of fixed width: each id takes the fewest bits that hold the vocabulary.

A shard is one file; its rows are blocks, in ascending document order. A block
holds whole documents: at least ``block_ids`` ids, unless the shard ends. Columns:
shard, block, first_id and last_id (least and greatest document id), start (ids of
the shard before it), n_ids, width, doc_ids, doc_starts (place of each document's
first id within the block), payload (id k in bits k*width to (k+1)*width, lowest
bit first, zero padding to whole bytes). Blocks lie in id order, so the range of
ids in the footers leads to a document's block, and the places of blocks and
documents lead to any token position; a block unpacks with a few numpy operations. Files are written by Spark's own committer, so a
lost executor leaves none half done, and to any store that Spark reaches.

Defined results: null and empty texts give just the end id; rows that repeat a
doc_id stand next to each other in the order of their texts; null ids come first; an empty table gives an
empty result; columns other than the two named ones play no part. A document
always lies in one block, so a very long one makes a long block.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import shared_path
from .tokens import encoder

BLOCK = "shard int, block int, first_id long, last_id long, start long, n_ids long, width int, doc_ids array<long>, doc_starts array<long>, payload binary"

ROW_GROUP_BYTES = 1 << 22


def width_of(vocab_size: int) -> int:
    return max(1, int(vocab_size - 1).bit_length())


def pack(ids: np.ndarray, width: int) -> bytes:
    if width in (8, 16, 32):
        return ids.astype(f"<u{width // 8}").tobytes()
    bits = (ids.astype(np.uint64)[:, None] >> np.arange(width, dtype=np.uint64)) & np.uint64(1)
    return np.packbits(bits.astype(np.uint8).ravel(), bitorder="little").tobytes()


def unpack(payload: bytes, width: int, first: int, n: int) -> np.ndarray:
    """Ids first to first + n - 1, without reading the others."""
    if width in (8, 16, 32):
        return np.frombuffer(payload, dtype=f"<u{width // 8}", count=n, offset=first * width // 8).astype("<u4")
    lo, hi = first * width, (first + n) * width
    bits = np.unpackbits(np.frombuffer(payload, np.uint8, count=-(-hi // 8) - lo // 8, offset=lo // 8), bitorder="little")
    bits = bits[lo % 8 : lo % 8 + n * width].reshape(n, width).astype(np.uint32)
    return (bits << np.arange(width, dtype=np.uint32)).sum(axis=1, dtype=np.uint32).astype("<u4")


def write_ids(docs: DataFrame, tokenizer: str, end_id: int, path: str, id_col: str = "doc_id", text_col: str = "text", block_ids: int = 1 << 16) -> None:
    """Encodes the texts, appends end_id to each, and writes shards in ascending id order."""
    end = np.array([end_id], dtype="<u4").tobytes()

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        enc, shard = encoder(tokenizer), TaskContext.get().partitionId()
        width = width_of(max(enc.vocab_size, end_id + 1))
        ids: list[int | None] = []
        starts: list[int] = []
        got: list[bytes] = []
        size = start = block = 0

        def flush() -> pa.RecordBatch:
            known = [i for i in ids if i is not None]
            first, last = (known[0], known[-1]) if known else (None, None)
            cols = [[shard], [block], [first], [last], [start], [size], [width], [ids], [starts], [pack(np.frombuffer(b"".join(got), "<u4"), width)]]
            types = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary()]
            names = ["shard", "block", "first_id", "last_id", "start", "n_ids", "width", "doc_ids", "doc_starts", "payload"]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)

        for b in batches:
            for i, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                mine = enc.encode(text.as_py() or "") + end
                ids.append(i)
                starts.append(size)
                got.append(mine)
                size += len(mine) // 4
                if size >= block_ids:
                    yield flush()
                    start, block, size, ids, starts, got = start + size, block + 1, 0, [], [], []
        if ids:
            yield flush()
        enc.release()

    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t"))
    ordered = rows.repartitionByRange("i").sortWithinPartitions("i", "t")
    # small row groups, so that a reader of one block skips the others of a file
    ordered.mapInArrow(blocks, BLOCK).write.option("compression", "zstd").option("parquet.block.size", ROW_GROUP_BYTES).parquet(path)


def shard_starts(blocks: DataFrame) -> DataFrame:
    """shard, base: the ids of all shards before it. A row for each file."""
    totals = blocks.groupBy("shard").agg(F.sum("n_ids").alias("n"))
    w = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    return totals.select("shard", F.coalesce(F.sum("n").over(w), F.lit(0)).alias("base"))


def read_documents(blocks: DataFrame) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens, ids (little-endian unsigned 32-bit), in file order."""

    def unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                n, starts = r["n_ids"], [*r["doc_starts"], r["n_ids"]]
                whole = unpack(r["payload"], r["width"], 0, n)
                at = r["base"] + r["start"]
                cols = [
                    pa.array(r["doc_ids"], pa.int64()),
                    pa.array([at + s for s in starts[:-1]], pa.int64()),
                    pa.array([e - s for s, e in zip(starts, starts[1:], strict=False)], pa.int64()),
                    pa.array([whole[s:e].tobytes() for s, e in zip(starts, starts[1:], strict=False)], pa.binary()),
                ]
                yield pa.RecordBatch.from_arrays(cols, ["doc_id", "start", "n_tokens", "ids"])

    rows = blocks.join(F.broadcast(shard_starts(blocks)), "shard")
    return rows.mapInArrow(unpacked, "doc_id long, start long, n_tokens long, ids binary")


def read_document(blocks: DataFrame, doc_id: int) -> np.ndarray | None:
    """Random access to one document's ids: the range of ids is pushed to the files, so only row groups that can hold it are read."""
    here = F.col("first_id").isNotNull() & (F.col("first_id") <= doc_id) & (F.col("last_id") >= doc_id)
    found = blocks.where(here & F.array_contains("doc_ids", doc_id)).select("doc_ids", "doc_starts", "n_ids", "width", "payload").first()
    if found is None:
        return None
    k = found["doc_ids"].index(doc_id)
    s, e = found["doc_starts"][k], [*found["doc_starts"], found["n_ids"]][k + 1]
    return unpack(bytes(found["payload"]), found["width"], s, e - s)


def read_span(blocks: DataFrame, start: int, n: int) -> np.ndarray:
    """Random access by position: n ids from the start-th of the whole corpus on (fewer at its end); of each block only the bits asked for are unpacked."""
    at = F.col("base") + F.col("start")
    met = blocks.join(F.broadcast(shard_starts(blocks)), "shard").withColumn("at", at).where((F.col("at") < start + n) & (F.col("at") + F.col("n_ids") > start))
    out = [np.zeros(0, "<u4")]
    for r in met.select("at", "n_ids", "width", "payload").orderBy("at").toLocalIterator():
        lo, hi = max(start - r["at"], 0), min(start + n - r["at"], r["n_ids"])
        out.append(unpack(bytes(r["payload"]), r["width"], lo, hi - lo))
    return np.concatenate(out)


def pack_corpus(docs: DataFrame, tokenizer: str, end_id: int, path: str | None = None, **options) -> DataFrame:
    """Writes the ids (to the shared folder unless path is given) and returns what the files hold, one row per block."""
    path = path or shared_path(docs.sparkSession, "token-ids")
    write_ids(docs, tokenizer, end_id, path, **options)
    return docs.sparkSession.read.schema(BLOCK).parquet(path)


def crc32_of(column: str = "ids"):
    """The unsigned CRC-32 of a binary column."""
    return F.crc32(F.col(column))


__all__ = ["crc32_of", "pack", "pack_corpus", "read_document", "read_documents", "read_span", "shard_starts", "unpack", "width_of", "write_ids"]
