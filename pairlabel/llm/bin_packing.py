"""Vector best-fit packing of token pieces into sequences.

A bin has three capacities: tokens, documents and attention cost (the sum of
squared lengths). Pieces are placed longest first, each into the bin that fits
best under every constraint: least weighted norm of the residual capacities, or
greatest weighted dot product of demand and residual, each capacity as a share of
its limit. A piece must fit an empty bin, so texts are cut at the length that all
three limits allow.

A piece's demand depends on its length alone, so the packing runs over the
histogram of lengths, which has at most as many entries as a sequence has tokens,
whatever the number of documents: bins in one state form one class with a count,
and each step fills as many of them as there are pieces. That gives what placing
the pieces one by one gives. Documents then find their place by their rank among
the pieces of their length, which is counted in parts and needs no global sort.

Defined results: null and empty texts give one piece with the end id alone;
repeated doc_ids are separate pieces; an empty table gives an empty result; columns
other than the two named ones play no part. A document longer than a sequence is
cut so that its first piece may be shorter and all others are full.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize
from .tokens import encoder

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


@dataclass(frozen=True)
class Capacity:
    """tokens: length of a sequence. docs, attention: None for what tokens imply. weights: of the three; mode: norm or dot."""

    tokens: int = 2048
    docs: int | None = 256
    attention: float | None = None
    weights: tuple[float, float, float] = (1.0, 1.0, 1.0)
    mode: str = "norm"

    def limits(self) -> np.ndarray:
        return np.array([self.tokens, self.docs or self.tokens, self.attention or float(self.tokens) ** 2])

    def piece(self) -> int:
        """The longest piece that an empty bin takes."""
        return max(1, min(self.tokens, int(np.floor(np.sqrt(self.limits()[2]) + 1e-9))))


def cut(length: int, size: int) -> list[tuple[int, int]]:
    """(start, length) of each piece."""
    if length <= size:
        return [(0, length)]
    first = length % size or size
    return [(0, first), *((s, size) for s in range(first, length, size))]


def token_pieces(docs: DataFrame, tokenizer: str, size: int = 2048, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = True) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, and the ids themselves (binary) if asked for."""
    end = np.array([end_id], dtype="<u4").tobytes()

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(tokenizer)
        for b in batches:
            out: list[tuple] = []
            for i, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = enc.encode(text.as_py() or "") + end
                for k, (s, n) in enumerate(cut(len(ids) // 4, size)):
                    own = ids[4 * s : 4 * (s + n)]
                    out.append((i, k, s, n, zlib.crc32(own), own if keep_ids else None))
            cols = list(zip(*out, strict=True)) or [()] * 6
            types = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()][: 6 if keep_ids else 5]
            names = ["doc_id", "piece", "start", "length", "ids_crc32", "ids"]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=False)], names[: len(types)])
        enc.release()

    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t"))
    return rows.mapInArrow(pieces, PIECES + (", ids binary" if keep_ids else ""))


def pack_histogram(counts: dict[int, int], capacity: Capacity = Capacity()) -> tuple[list[tuple[int, int, int, int, int, int]], int]:
    """Slots (length, first rank, pieces, first sequence, pieces per sequence, offset), and the number of sequences.

    The piece of rank r lies in sequence first + (r - first rank) // per, at offset + (r - first rank) % per * length.
    """
    limits = capacity.limits()
    weights = np.array(capacity.weights) / limits
    left = np.zeros((0, 3))  # residual capacities by class of bins
    many: list[int] = []
    first: list[int] = []
    slots, used = [], 0
    for length in sorted(counts, reverse=True):
        demand = np.array([length, 1.0, float(length) ** 2])
        todo, rank = counts[length], 0
        most = int(np.min(limits // demand))
        if most < 1:
            raise ValueError(f"a piece of length {length} exceeds a capacity")
        while todo:
            fits = np.nonzero((left >= demand).all(axis=1))[0] if len(left) else []
            if len(fits):
                if capacity.mode == "dot":
                    best = fits[np.argmax((left[fits] * demand * weights**2).sum(axis=1))]
                else:
                    best = fits[np.argmin((((left[fits] - demand) * weights) ** 2).sum(axis=1))]
                # under the norm a bin that has just been filled fits better still, so it goes on filling
                per = int(np.min(left[best] // demand)) if capacity.mode == "norm" else 1
                room, at, base = many[best], left[best], first[best]
            else:
                best, per, at, base = None, most if capacity.mode == "norm" else 1, limits.astype(float), used
                room = -(-todo // per)
                used += room
            per = min(per, todo)
            bins = min(todo // per, room)
            offset = int(limits[0] - at[0])
            slots.append((length, rank, bins * per, base, per, offset))
            rank, todo = rank + bins * per, todo - bins * per
            filled = at - per * demand
            if best is None:
                left, many, first = np.vstack([left, filled]), [*many, bins], [*first, base]
                if room > bins:  # opened but not filled yet
                    left, many, first = np.vstack([left, at]), [*many, room - bins], [*first, base + bins]
            elif bins == room:
                left[best] = filled
            else:
                many[best], first[best] = room - bins, base + bins
                left, many, first = np.vstack([left, filled]), [*many, bins], [*first, base]
        open_ = left[:, 0] >= 1
        if not open_.all():
            keep = np.nonzero(open_)[0]
            left, many, first = left[keep], [many[k] for k in keep], [first[k] for k in keep]
    return slots, used


def ranked(pieces: DataFrame, part_rows: int = 100_000) -> DataFrame:
    """Adds rank: from 0 within the pieces of one length, without gaps. Parts are counted, then ranked apart."""
    total = pieces.count()
    parts = max(8, total // part_rows)
    rows = pieces.withColumn("_part", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(parts)).cast("int"))
    sizes = rows.groupBy("length", "_part").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy("length").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    bases = sizes.select("length", "_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base"))
    within = Window.partitionBy("length", "_part").orderBy("doc_id", "piece")
    rows = rows.withColumn("_k", F.row_number().over(within) - 1)
    return rows.join(bases, ["length", "_part"]).withColumn("rank", F.col("_base") + F.col("_k")).drop("_part", "_base", "_k")


def pack_pieces(pieces: DataFrame, capacity: Capacity = Capacity()) -> DataFrame:
    """Adds sequence_id and offset to a table of pieces with doc_id, piece and length. Read it from storage: it is read three times."""
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most capacity.tokens rows
    slots, _ = pack_histogram(counts, capacity)
    table = np.array(sorted(slots), dtype=np.int64).reshape(-1, 6)
    rows = ranked(pieces)
    names = rows.columns

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys = table[:, 0] << 44 | table[:, 1]
        for b in batches:
            length = b.column(names.index("length")).to_numpy(zero_copy_only=False)
            rank = b.column(names.index("rank")).to_numpy(zero_copy_only=False)
            hit = table[np.searchsorted(keys, length << 44 | rank, side="right") - 1] if len(length) else table[:0]
            k = rank - hit[:, 1]
            sequence, offset = hit[:, 3] + k // hit[:, 4], hit[:, 5] + k % hit[:, 4] * length
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(sequence, pa.int64()), pa.array(offset, pa.int64())], [*names, "sequence_id", "offset"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields)
    return rows.mapInArrow(place, f"{schema}, sequence_id long, offset long").drop("rank")


def pack_documents(docs: DataFrame, tokenizer: str, capacity: Capacity = Capacity(), end_id: int = 0, keep_ids: bool = True, **options) -> DataFrame:
    """Tokenises once into the shared folder, then packs. One row per piece."""
    pieces = materialize(token_pieces(docs, tokenizer, capacity.piece(), end_id, keep_ids=keep_ids, **options), "pieces")
    return pack_pieces(pieces, capacity)


def sequences(packed: DataFrame) -> DataFrame:
    """sequence_id, ids (the pieces in their places), n_tokens, n_pieces. A sequence is of bounded size."""
    own = F.array_sort(F.collect_list(F.struct("offset", "ids")))
    return packed.groupBy("sequence_id").agg(own.alias("s"), F.sum("length").alias("n_tokens"), F.count(F.lit(1)).alias("n_pieces")).select(
        "sequence_id", F.unhex(F.array_join(F.transform("s.ids", F.hex), "")).alias("ids"), "n_tokens", "n_pieces"
    )
