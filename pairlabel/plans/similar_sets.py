"""Components of similar sets without a table of candidate pairs.

1. Tokens are 64-bit hashes (two of V tokens agree with a chance of V * V / 2^65).
   Those that two sets or more have are numbered by frequency, the most frequent first;
   if they are more than ``MAX_NUMBERED``, the rarer ones keep their hashes. A token of
   one set alone only counts for the size.
2. Equal sets are one class. Classes are dealt into blocks by size, so that a block has a
   bounded number of tokens, and a task gets two blocks that could have similar sets.
3. In a task the smaller set asks: of two sets with Jaccard t or more, sizes a <= b, the
   first a - ceil(2t / (1 + t) * a) + 1 and b - ceil(t * b) + 1 tokens, rarest first, have
   one in common, behind which enough must be left of both. Bit signatures then bound the
   overlap from above, and what is left is compared exactly, unless the task has joined
   both already. A task returns at most one link less than it has sets.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .planner import cut

#: Bounds the broadcast of token numbers.
MAX_NUMBERED = 2_000_000
#: Tokens of a block, with so many for each set besides.
BLOCK, PER_SET = 6_000_000, 64
#: Above this many tokens there are at least so many blocks.
SMALL, LEAST_BLOCKS = 500_000, 6
#: Sets that ask at a time, and how many meetings these may have.
ASK, MEETINGS = 256, 4_000_000

_SETS = "rec_id long, n int, digest binary, near binary, far binary, rest binary"


def numbered(sets: DataFrame, max_numbered: int = MAX_NUMBERED) -> tuple[np.ndarray, np.ndarray, bool]:
    """Hashes (ascending) and their numbers, of the tokens that two rows of (rec_id, h) or more have; whether these are all of them."""
    df = cut(sets.select(F.explode("h").alias("h")).groupBy("h").agg(F.count(F.lit(1)).alias("df")).where("df > 1"), "df")
    least, room = None, max_numbered
    for r in sorted(df.groupBy("df").count().collect(), reverse=True):
        room -= r["count"]
        if room < 0:
            break
        least = r["df"]
    whole = room >= 0
    got = df.where(F.col("df") >= (least or 1 << 62)).toArrow()
    h, n = got.column("h").to_numpy(), got.column("df").to_numpy()
    number = np.empty(len(h), np.int64)
    number[np.lexsort((h, -n))] = np.arange(len(h))
    order = np.argsort(h)
    return h[order], number[order], whole


def _coded(ids, lists, hashes, number, whole) -> pa.RecordBatch:
    offsets = lists.offsets.to_numpy().astype(np.int64)
    flat = lists.values.to_numpy(zero_copy_only=False)[offsets[0] : offsets[-1]]
    offsets = offsets - offsets[0]
    doc = np.repeat(np.arange(len(ids)), np.diff(offsets))
    at = np.searchsorted(hashes, flat)
    at[at == len(hashes)] = 0
    known = hashes[at] == flat if len(hashes) else np.zeros(len(flat), bool)
    d, v = doc[known], number[at[known]] if len(hashes) else np.zeros(0, np.int64)
    o = np.lexsort((v, d))
    d, v = d[o], v[o]
    first = np.searchsorted(d, np.arange(len(ids) + 1))
    step = np.diff(v, prepend=0)
    begin = first[:-1][first[:-1] < first[1:]]
    step[begin] = v[begin]
    near, far = np.minimum(step, 255).astype(np.uint8), step.astype(np.uint32)
    digest, out = [], ([], [], [])
    for k in range(len(ids)):
        own = flat[offsets[k] : offsets[k + 1]]
        digest.append(hashlib.blake2b(np.sort(own).tobytes(), digest_size=16).digest() if len(own) else None)
        s = slice(first[k], first[k + 1])
        out[0].append(near[s].tobytes())
        out[1].append(far[s][near[s] == 255].tobytes())
        out[2].append(b"" if whole else np.sort(own[~known[offsets[k] : offsets[k + 1]]]).tobytes())
    cols = [ids, pa.array(np.diff(offsets), pa.int32()), pa.array(digest, pa.binary()), *[pa.array(x, pa.binary()) for x in out]]
    return pa.RecordBatch.from_arrays(cols, ["rec_id", "n", "digest", "near", "far", "rest"])


def hashed_sets(sets: DataFrame) -> DataFrame:
    """Of (rec_id, s: distinct tokens) and further columns: rec_id, h (64-bit hashes of the tokens), and these."""
    return sets.select(F.col("rec_id").cast("long").alias("rec_id"), F.transform("s", lambda t: F.xxhash64(t)).alias("h"), *[c for c in sets.columns if c not in ("rec_id", "s")])


def coded_tables(*hashed: DataFrame, max_numbered: int = MAX_NUMBERED) -> list[DataFrame]:
    """coded_sets of several tables from hashed_sets, numbered together, so that sets of different tables compare; further columns go along."""
    every = hashed[0].select("rec_id", "h")
    for h in hashed[1:]:
        every = every.unionAll(h.select("rec_id", "h"))
    hashes, number, whole = numbered(every, max_numbered)
    sent = every.sparkSession.sparkContext.broadcast((hashes, number))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(0, b.num_rows, 500):
                part = b.slice(k, 500)
                out = _coded(part.column(0), part.column(1), *sent.value, whole)
                yield pa.RecordBatch.from_arrays([*out.columns, *part.columns[2:]], [*out.schema.names, *part.schema.names[2:]])

    return [h.mapInArrow(run, T.StructType([*T.StructType.fromDDL(_SETS).fields, *h.schema.fields[2:]])) for h in hashed]


def coded_sets(sets: DataFrame, max_numbered: int = MAX_NUMBERED) -> DataFrame:
    """rec_id, n, digest (null if empty) and the token numbers of each row of (rec_id, s: distinct tokens): steps below 255 in near, the others in far, hashes without a number in rest."""
    return coded_tables(hashed_sets(sets), max_numbered=max_numbered)[0]


def _keys(near: list[bytes], far: list[bytes]) -> np.ndarray:
    """Row in the upper, token number in the lower 32 bits; ascending."""
    step = np.frombuffer(b"".join(near), np.uint8).astype(np.int64)
    step[step == 255] = np.frombuffer(b"".join(far), np.uint32)
    size = np.array([len(x) for x in near], np.int64)
    total, start = np.concatenate([[0], np.cumsum(step)]), np.concatenate([[0], np.cumsum(size)])
    return np.repeat(np.arange(len(size)) << 32, size) + total[1:] - np.repeat(total[start[:-1]], size)


def shared_tokens(near_a, far_a, rest_a, near_b, far_b, rest_b) -> np.ndarray:
    """How many tokens the sets of each row share; both come from one call of coded_tables."""
    met = np.sort(np.concatenate([_keys(near_a, far_a), _keys(near_b, far_b)]), kind="stable")
    out = np.bincount(met[1:][met[1:] == met[:-1]] >> 32, minlength=len(near_a))
    for k, (x, y) in enumerate(zip(rest_a, rest_b, strict=True)):
        if x and y:
            out[k] += len(np.intersect1d(np.frombuffer(x, np.int64), np.frombuffer(y, np.int64), assume_unique=True))
    return out


@F.pandas_udf(T.LongType())
def shared_size(near_a: pd.Series, far_a: pd.Series, rest_a: pd.Series, near_b: pd.Series, far_b: pd.Series, rest_b: pd.Series) -> pd.Series:
    sides = [c.tolist() for c in (near_a, far_a, rest_a, near_b, far_b, rest_b)]
    return pd.Series(np.concatenate([np.zeros(0, np.int64), *(shared_tokens(*(c[k : k + 1000] for c in sides)) for k in range(0, len(near_a), 1000))]))


def in_blocks(heads: DataFrame, threshold: float, block: int = BLOCK, small: int = SMALL) -> tuple[DataFrame, int]:
    """The sets with pair and side, a row for each pair of blocks that a set is in; how many pairs there are. No set of a pair's first block is larger than one of its second."""
    sizes = sorted((r["n"], r["count"]) for r in heads.groupBy("n").count().collect())
    weight = [(n, c * (n + PER_SET)) for n, c in sizes]
    total = sum(w for _, w in weight)
    g = max(1, -(-total // block), LEAST_BLOCKS if total > small else 1)
    least, most, rows, before = {}, {}, [], 0
    for n, w in weight:
        rows.append((n, float(before * g / total), float(w * g / total)))
        for b in range(int(before * g / total), min(g - 1, int((before + w) * g / total)) + 1):
            least.setdefault(b, n)
            most[b] = n
        before += w
    pairs = [(i, j) for i in most for j in most if i <= j and least[j] * threshold <= most[i] + 1e-9]
    of: dict[int, list] = {b: [] for b in most}
    for k, (i, j) in enumerate(pairs):
        of[i].append((k, 0))
        if i != j:
            of[j].append((k, 1))
    spark = heads.sparkSession
    place = F.broadcast(spark.createDataFrame(rows, "n int, at double, width double"))
    asked = F.broadcast(spark.createDataFrame([(b, k, side) for b, own in of.items() for k, side in own], "block int, pair int, side int"))
    u = F.pmod(F.xxhash64("rec_id"), F.lit(1_000_000)) / F.lit(1e6)
    at = heads.join(place, "n").withColumn("block", F.least(F.lit(g - 1), F.floor(F.col("at") + u * F.col("width"))).cast("int"))
    return at.join(asked, "block").select("pair", "side", "rec_id", "n", "near", "far", "rest"), len(pairs)


class _Sets:
    """Sets in the order of size; the tokens of each, rarest first."""

    def __init__(self, table: pa.Table):
        n, ids = table.column("n").to_numpy(), table.column("rec_id").to_numpy()
        order = np.lexsort((ids, n))
        self.ids, self.n = ids[order], n[order].astype(np.int64)
        near, far, rest = ([x[k] for k in order] for x in (table.column(c).to_pylist() for c in ("near", "far", "rest")))
        step = np.frombuffer(b"".join(near), np.uint8).astype(np.int64)
        step[step == 255] = np.frombuffer(b"".join(far), np.uint32)
        size = np.array([len(x) for x in near], np.int64)
        total, start = np.concatenate([[0], np.cumsum(step)]), np.concatenate([[0], np.cumsum(size)])
        code = total[1:] - np.repeat(total[start[:-1]], size)
        row = np.repeat(np.arange(len(size)), size)
        loose = np.frombuffer(b"".join(rest), np.int64)
        if len(loose):  # behind all numbers, so the rarest
            code = np.concatenate([code, loose])
            row = np.concatenate([row, np.repeat(np.arange(len(size)), [len(x) // 8 for x in rest])])
        self.loose = np.arange(len(code)) >= len(step)
        self.code, self.row = code, row

    def arrange(self, names: np.ndarray, top: int) -> None:
        """Numbers for hashes, then the order."""
        self.code[self.loose] = top + np.searchsorted(names, self.code[self.loose])
        o = np.lexsort((-self.code, self.row))
        self.code, self.row = self.code[o], self.row[o]
        self.start = np.searchsorted(self.row, np.arange(len(self.n) + 1))
        self.held = np.diff(self.start)
        self.at = np.arange(len(self.code)) - self.start[self.row] + (self.n - self.held)[self.row]  # tokens of one set alone stand first

    def tokens(self, k: int) -> np.ndarray:
        return self.code[self.start[k] : self.start[k + 1]][::-1]

    def signatures(self, bits: int) -> np.ndarray:
        on = np.zeros((len(self.n), bits), bool)
        on[self.row, (self.code * 0x9E3779B1 >> 7) % bits] = True
        return np.packbits(on, axis=1).view(np.uint64)


def _ranges(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    return np.repeat(begin - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(size.sum())


def links_between(a: _Sets, b: _Sets, t: float) -> list[tuple[int, int]]:
    """A spanning forest of the links of a's sets with b's (which may be a itself)."""
    within = a is b
    loose = np.unique(np.concatenate([x.code[x.loose] for x in (a, b)]))
    top = max([int(x.code[~x.loose].max()) + 1 for x in (a, b) if (~x.loose).any()], default=0)
    for x in (a,) if within else (a, b):
        x.arrange(loose, top)
    share, m = t / (1 + t), len(b.n)
    if not m or not len(a.n):
        return []
    whole = lambda x: np.ceil(x - 1e-9).astype(np.int64)
    post = np.nonzero(b.at < (b.n - whole(t * b.n) + 1)[b.row])[0]
    post = post[np.lexsort((b.row[post], b.code[post]))]
    key, rows = b.code[post] * m + b.row[post], b.row[post]
    slack = (b.n[rows] - b.at[post] - share * b.n[rows] + 1e-6).astype(np.float32)
    ask = np.nonzero(a.at < (a.n - whole(2 * share * a.n) + 1)[a.row])[0]
    ask_n, ask_row = a.n[a.row[ask]], a.row[ask]
    most = np.minimum(ask_n / t, (ask_n - a.at[ask]) / share - ask_n) + 1e-6  # the largest size that leaves enough
    first = np.searchsorted(key, a.code[ask] * m + (ask_row + 1 if within else 0))
    size = np.maximum(np.searchsorted(key, a.code[ask] * m + np.searchsorted(b.n, most, "right")) - first, 0)
    ask, ask_row, first, size = (x[size > 0] for x in (ask, ask_row, first, size))
    bits = 1 << max(8, math.ceil(math.log2(4 * float(np.median(b.held)) + 1)))
    sig_a = a.signatures(min(bits, 1 << 14))
    sig_b = sig_a if within else b.signatures(min(bits, 1 << 14))
    shift = 0 if within else len(a.n)
    root = np.arange(shift + m)
    out = []
    asked = np.searchsorted(ask_row, np.arange(len(a.n) + 1))
    load = np.concatenate([[0], np.cumsum(size)])[asked]
    k = 0
    while k < len(a.n):
        end = min(k + ASK, len(a.n), max(k + 1, int(np.searchsorted(load, load[k] + MEETINGS, "right")) - 1))
        s = slice(asked[k], asked[end])
        if s.start < s.stop:
            met = _ranges(first[s], size[s])
            of = np.repeat(ask_row[s], size[s])
            near = slack[met] >= (share * a.n).astype(np.float32)[of] - 1e-3
            mark = np.zeros((end - k) * m, bool)
            mark[(of[near] - k) * m + rows[met[near]]] = True
            x, y = np.divmod(np.nonzero(mark)[0], m)
            _compare(a, b, x + k, y, t, share, sig_a, sig_b, root, shift, out)
        k = end
    return out


def _compare(a, b, x, y, t, share, sig_a, sig_b, root, shift, out) -> None:
    keep = []
    step = max(1, (1 << 22) // sig_a.shape[1])
    for k in range(0, len(x), step):
        p, q = x[k : k + step], y[k : k + step]
        apart = root[p] != root[q + shift]
        p, q = p[apart], q[apart]
        s, r = sig_a[p], sig_b[q]
        need = (a.n[p] + b.n[q]) * share - 1e-6
        both = s & r
        one = np.bitwise_count(s ^ both).sum(1, dtype=np.int64)
        two = np.bitwise_count(r ^ both).sum(1, dtype=np.int64)
        ok = (a.held[p] - one >= need) & (b.held[q] - two >= need)
        keep.append((p[ok], q[ok]))
    x, y = (np.concatenate([w[j] for w in keep] or [np.zeros(0, np.int64)]) for j in (0, 1))
    tries = 1
    while len(x):
        turn = np.arange(len(x)) - np.searchsorted(x, x)
        for p, q in zip(x[turn < tries].tolist(), y[turn < tries].tolist(), strict=True):
            if root[p] == root[q + shift]:
                continue
            s, r = a.tokens(p), b.tokens(q)
            at = np.searchsorted(r, s)
            at[at == len(r)] = 0
            c = int(np.count_nonzero(r[at] == s)) if len(r) else 0
            if c / (a.n[p] + b.n[q] - c) >= t:
                root[root == root[q + shift]] = root[p]
                out.append((int(a.ids[p]), int(b.ids[q])))
        rest = (turn >= tries) & (root[x] != root[y + shift])
        x, y, tries = x[rest], y[rest], 2 * tries


def links(heads: DataFrame, threshold: float, block: int = BLOCK, small: int = SMALL) -> DataFrame:
    """id_a, id_b: similar pairs of coded sets, which are distinct and not empty; they have the same components as all similar pairs."""
    rows, n = in_blocks(heads, threshold, block, small)

    def run(table: pa.Table) -> pa.Table:
        side = table.column("side").to_numpy()
        a = _Sets(table.filter(pa.array(side == 0)))
        b = _Sets(table.filter(pa.array(side == 1))) if side.any() else a
        found = links_between(a, b, threshold)
        return pa.table({"id_a": pa.array([x for x, _ in found], pa.int64()), "id_b": pa.array([y for _, y in found], pa.int64())})

    return rows.repartition(max(1, n), "pair").groupBy("pair").applyInArrow(run, "id_a long, id_b long")
