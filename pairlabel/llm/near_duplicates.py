"""Exact n-gram Jaccard join over a token-group matrix.

A document's set holds the hashes of its distinct runs of five words. Two
documents link when 100 * intersection >= 75 * union. The result is the connected
components; links that join what is joined already are not all listed, but none
that joins different components is ever lost.

1. Classes. Documents with equal sets form a class, found by a 128-bit digest; one
   row per class goes on.
2. Pruning. Of each class the ``p`` least hashes are posted by hash. With
   p = size - ceil(0.75 size) + l(size), any two linked classes share at least
   l - 1 of what both have posted, so a class with fewer shared postings has no
   link and leaves. Nothing but counts comes back.
3. Groups. The rest are gathered by least hash, and each is compared with a bounded
   number of leaders; a verified link puts it into its leader's group. This only
   saves work: similar documents form groups, which are split into blocks of
   bounded size.
4. Matrix. For each token the groups that hold it are counted. Each document's
   tokens are put in order, fewest groups first; of two linked documents the
   smaller one asks, and its first size - ceil(6/7 size) + 1 tokens and the larger one's first
   size - ceil(3/4 size) + 1 share one. That token leads from it to the
   blocks of other groups. Each block that is asked has its members' token union
   stored; the document's overlap with it bounds that with every member, and only
   of blocks that reach the needed overlap are the members read and compared exactly.
5. Components of groups by the links found.

Skew: a group of equal texts is one class; near copies of one text meet only
leaders and have tokens that no other group holds; a passage that many documents
share comes last in the order of tokens, or is behind the bound of positions. Keys
by which documents meet leaders, and blocks that many documents ask, are split by
their counted sizes, so no task gets much more than a thousandth of all rows.

Sets hold 64-bit hashes: two given sets of a and b shingles have a wrong one in
common with a chance of at most a * b / 2^64, under 10^-11 for 10,000 shingles each.

Defined results: null and empty texts, and texts without words, have no shingles
and are a component of their own; rows with a null id get a null component;
repeated ids are one document for the components; an empty table gives an empty
result; columns other than the two named ones play no part.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hot_join, materialize
from .shingles import mix, shingle_sets, text_slices

_U = np.uint64
#: Linked when SHARE[1] * intersection >= SHARE[0] * union.
SHARE = (75, 100)


def least_overlap(size, share=SHARE):
    """With any partner: ceil(share * size)."""
    return -(-size * share[0] // share[1])


def pair_overlap(a, b, share=SHARE):
    """The intersection that two sets of these sizes need."""
    return -(-(a + b) * share[0] // (share[0] + share[1]))


def spare(size):
    """How many postings beyond the shortest prefix; l of the module's text."""
    return np.maximum(1, size // 10)


def linked(a: np.ndarray, b: np.ndarray, share=SHARE) -> bool:
    """Exact, for sorted distinct sets."""
    need = pair_overlap(len(a), len(b), share)
    if need > min(len(a), len(b)):
        return False
    small, large = (a, b) if len(a) <= len(b) else (b, a)
    at = np.searchsorted(large, small)
    at[at == len(large)] = 0
    both = int(np.count_nonzero(large[at] == small))
    return both >= need


def _sets(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[tuple[list, list[np.ndarray]]]:
    """Ids and sets, slice by slice, of batches of (id, text)."""
    for b in batches:
        ids = b.column(0)
        for first, raw, offsets in text_slices(b.column(1)):
            sets = list(shingle_sets(raw, offsets, size))
            yield ids.slice(first, len(sets)).to_pylist(), sets


def _digest(s: np.ndarray) -> bytes:
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


def members_of(docs: DataFrame, size: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, digest of each row; digest is null for empty sets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, sets in _sets(batches, size):
            digests = [_digest(s) if len(s) else None for s in sets]
            cols = [pa.array(ids, pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.array(digests, pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, ["doc_id", "n_shingles", "digest"])

    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t"))
    return rows.mapInArrow(run, "doc_id long, n_shingles long, digest binary")


def _blobs(owners: list[bytes], tokens: list[np.ndarray], n_buckets: int) -> Iterator[tuple[int, bytes, bytes, bytes]]:
    """Tokens by bucket: bucket, tokens, number of each one's owner, owners. Equal numbers of bytes per owner."""
    if not tokens:
        return
    all_ = np.concatenate(tokens)
    own = np.repeat(np.arange(len(tokens), dtype=np.uint32), [len(t) for t in tokens])
    bucket = (mix(all_) % _U(n_buckets)).astype(np.int64)
    order = np.argsort(bucket, kind="stable")
    all_, own, bucket = all_[order], own[order], bucket[order]
    cuts = np.nonzero(np.diff(bucket))[0] + 1
    for t, o, b in zip(np.split(all_, cuts), np.split(own, cuts), bucket[np.concatenate([[0], cuts])] if len(bucket) else [], strict=True):
        used, small = np.unique(o, return_inverse=True)
        width = np.uint16 if len(used) < 1 << 16 else np.uint32
        yield int(b), t.tobytes(), small.astype(width).tobytes(), b"".join(owners[k] for k in used.tolist())


_BLOB = "bucket int, tokens binary, owner binary, owners binary"


def _blob_batch(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [(), (), (), ()]
    types = [pa.int32(), pa.binary(), pa.binary(), pa.binary()]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], ["bucket", "tokens", "owner", "owners"])


def _open_blobs(table: pa.Table, owner_bytes: int) -> tuple[np.ndarray, np.ndarray]:
    """All tokens of a bucket, and for each its owner as a row of 64-bit numbers."""
    tokens, owners = [], []
    for t, o, refs in zip(*(table.column(c).to_pylist() for c in ("tokens", "owner", "owners")), strict=True):
        ref = np.frombuffer(refs, np.int64).reshape(-1, owner_bytes // 8)
        k = np.frombuffer(o, np.uint16 if len(ref) < 1 << 16 else np.uint32)
        tokens.append(np.frombuffer(t, _U))
        owners.append(ref[k])
    return np.concatenate(tokens), np.concatenate(owners)


def prune(docs: DataFrame, classes: DataFrame, total: int, size: int = 5, id_col: str = "doc_id", text_col: str = "text", bucket_tokens: int = 1 << 20) -> DataFrame:
    """Of classes (digest, rid, n, copies) those that may have a link to another."""
    n_buckets = max(1, total * 2 // 5 // bucket_tokens + 1)
    n_ranges = max(1, total // 400 // 200_000 + 1)

    def post(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[bytes, np.ndarray] = {}
        n = 0
        for _, sets in _sets(batches, size):
            for s in sets:
                if len(s) and (d := _digest(s)[:8] + len(s).to_bytes(8, "little")) not in held:
                    held[d] = s[: len(s) - least_overlap(len(s)) + int(spare(len(s)))].copy()
                    n += len(held[d])
            if n > 1 << 20:
                yield _blob_batch(list(_blobs(list(held), list(held.values()), n_buckets)))
                held, n = {}, 0
        yield _blob_batch(list(_blobs(list(held), list(held.values()), n_buckets)))

    def shared(table: pa.Table) -> pa.Table:
        """Of one bucket of tokens: counts of shared postings by class, a row per range of classes."""
        tokens, owners = _open_blobs(table, 16)
        order = np.lexsort((owners[:, 0], tokens))
        tokens, owners = tokens[order], owners[order]
        refs = owners[:, 0]
        new_token = np.concatenate([[True], tokens[1:] != tokens[:-1]])
        new = new_token | np.concatenate([[True], refs[1:] != refs[:-1]])
        owners, new_token = owners[new], new_token[new]
        group = np.cumsum(new_token) - 1
        several = np.bincount(group) > 1
        owners = owners[several[group]]
        refs, first, counts = np.unique(owners[:, 0], return_index=True, return_counts=True)
        sizes = owners[first, 1]
        part = (refs.view(_U) % _U(n_ranges)).astype(np.int64)
        own = [part == k for k in np.unique(part).tolist()]
        return pa.table({
            "part": pa.array(np.unique(part), pa.int64()),
            "refs": pa.array([refs[k].tobytes() for k in own], pa.binary()),
            "sizes": pa.array([sizes[k].astype(np.int64).tobytes() for k in own], pa.binary()),
            "counts": pa.array([counts[k].astype(np.int64).tobytes() for k in own], pa.binary()),
        })

    def enough(table: pa.Table) -> pa.Table:
        refs, sizes, counts = (np.concatenate([np.frombuffer(x, np.int64) for x in table.column(c).to_pylist()]) for c in ("refs", "sizes", "counts"))
        own, first, where = np.unique(refs, return_index=True, return_inverse=True)
        total_ = np.bincount(where, counts)
        least = np.maximum(1, spare(sizes[first]) - 1)
        return pa.table({"ref": pa.array(own[total_ >= least], pa.int64())})

    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t"))
    counted = rows.mapInArrow(post, _BLOB).groupBy("bucket").applyInArrow(shared, "part long, refs binary, sizes binary, counts binary")
    refs = counted.groupBy("part").applyInArrow(enough, "ref long")
    # the first eight bytes of the digest, read as a little-endian 64-bit number
    hexed = F.hex(F.substring("digest", 1, 8))
    turned = F.concat(*[F.substring(hexed, 15 - 2 * k, 2) for k in range(8)])
    signed = F.conv(turned, 16, -10).cast("decimal(20,0)").cast("long")
    return classes.withColumn("ref", signed).join(refs, "ref", "left_semi").select("digest", "rid", "n")


_SET = "rid long, n long, tokens binary"


def survivor_sets(docs: DataFrame, survivors: DataFrame, n_survivors: int, size: int, id_col: str, text_col: str, broadcast_rows: int = 300_000) -> DataFrame:
    """rid, n, tokens, least, second (least hashes under two orders) of each surviving class; ids are broadcast only where they are few."""
    ids = survivors.select(F.col("rid").alias("i"))
    ids = F.broadcast(ids) if n_survivors <= broadcast_rows else ids
    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")).join(ids, "i", "left_semi")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for own, sets in _sets(batches, size):
            pairs = [(i, s) for i, s in zip(own, sets, strict=True) if len(s)]
            cols = [
                pa.array([i for i, _ in pairs], pa.int64()),
                pa.array([len(s) for _, s in pairs], pa.int64()),
                pa.array([s.tobytes() for _, s in pairs], pa.binary()),
                pa.array([int(s[0].astype(np.int64)) for _, s in pairs], pa.int64()),
                pa.array([int(mix(s ^ _U(0x5851F42D4C957F2D)).min().astype(np.int64)) for _, s in pairs], pa.int64()),
            ]
            yield pa.RecordBatch.from_arrays(cols, ["rid", "n", "tokens", "least", "second"])

    return rows.mapInArrow(run, f"{_SET}, least long, second long")


def _central_first(sets: list[np.ndarray]) -> list[int]:
    """Those whose tokens most others share come first."""
    if len(sets) < 3:
        return list(range(len(sets)))
    _, where, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    own = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    mean = np.bincount(own, counts[where]) / np.array([len(s) for s in sets])
    return np.argsort(-mean, kind="stable").tolist()


def follow_leaders(sets: DataFrame, most: int = 48, buffered: int = 256) -> DataFrame:
    """rid, leader: documents compared, within one value of the column key, with at most so many leaders; only verified links count.

    Leaders are picked among the first ``buffered`` documents of a key, the most central first, as they link to most of the others.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, leaders, waiting = None, [], []
        out: list[tuple[int, int]] = []

        def meet(rid: int, s: np.ndarray) -> None:
            sketch = set(s[:24].tolist())
            for j, (lead, t, other) in enumerate(leaders):
                if len(sketch & other) * 4 >= min(len(sketch), len(other)) and linked(s, t):
                    out.append((rid, lead))
                    if j:
                        leaders.insert(0, leaders.pop(j))
                    return
            if len(leaders) < most:
                leaders.append((rid, s, sketch))

        def settle() -> None:
            if len(waiting) > 1:
                for k in _central_first([s for _, s in waiting]):
                    meet(*waiting[k])
            elif waiting and most:
                leaders.append((waiting[0][0], waiting[0][1], set(waiting[0][1][:24].tolist())))
            waiting.clear()

        def flush() -> pa.RecordBatch:
            got = pa.RecordBatch.from_arrays([pa.array([x[0] for x in out], pa.int64()), pa.array([x[1] for x in out], pa.int64())], ["rid", "leader"])
            out.clear()
            return got

        full = False
        for b in batches:
            for rid, blob, k in zip(*(b.column(c).to_pylist() for c in ("rid", "tokens", "key")), strict=True):
                if k != last:
                    settle()
                    last, full = k, False
                    leaders.clear()
                s = np.frombuffer(blob, _U)
                if full:
                    meet(rid, s)
                    continue
                waiting.append((rid, s))
                if len(waiting) >= buffered:
                    settle()
                    full = True
            yield flush()
        settle()
        yield flush()

    rows = sets.select("rid", "tokens", "key").repartition("key").sortWithinPartitions("key", "rid")
    return rows.mapInArrow(run, "rid long, leader long")


#: A key or a block is hot with over one in so many of all rows, so at most so many are.
HOT_PARTS = 1000


def split_hot(sets: DataFrame, key, part_rows: int, total: int) -> DataFrame:
    """The sets with a column key: that given, but for hot keys, of which parts of bounded size get keys of their own."""
    most = max(part_rows, -(-total // HOT_PARTS))
    keyed = sets.withColumn("_k", key)
    hot = keyed.groupBy("_k").agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") > most).select("_k", F.ceil(F.col("_n") / most).alias("_parts"))
    part = F.pmod(F.xxhash64("rid", F.lit(7)), F.coalesce("_parts", F.lit(1)))
    return keyed.join(F.broadcast(hot), "_k", "left").withColumn("key", F.when(F.col("_parts").isNull(), F.col("_k")).otherwise(F.xxhash64("_k", part))).drop("_k", "_parts")


def grouped(sets: DataFrame, salts: int = 8, block_rows: int = 256, leaders: int = 48, part_rows: int = 256) -> DataFrame:
    """The sets with group (a leader's id) and block (a part of the group, of bounded size). Labels are joined without the sets, hot ones spread."""
    salted, total = F.xxhash64("least", F.pmod(F.xxhash64("rid"), F.lit(salts))), sets.count()
    led = materialize(follow_leaders(split_hot(sets, salted, part_rows, total), leaders), "leaders-1")
    left = sets.join(led.select("rid"), "rid", "left_anti")
    led2 = materialize(follow_leaders(split_hot(left, F.col("least"), 4 * part_rows, total), leaders), "leaders-2")
    left = left.join(led2.select("rid"), "rid", "left_anti")
    led3 = materialize(follow_leaders(split_hot(left, F.col("second"), 4 * part_rows, total), leaders), "leaders-3")

    def follow(rows: DataFrame, further: DataFrame) -> DataFrame:
        """rid, leader with each leader replaced by the one it follows itself."""
        sizes = rows.groupBy("leader").agg(F.count(F.lit(1)).alias("_n"))
        onward = sizes.join(further.select(F.col("rid").alias("leader"), F.col("leader").alias("_to")), "leader", "left")
        out = hot_join(rows, onward, "leader", "_n", rows.count(), F.col("rid"))
        return out.select("rid", F.coalesce("_to", "leader").alias("leader"))

    later = led3.unionByName(follow(led2, led3))
    names = materialize(follow(led, later).unionByName(later).dropDuplicates(["rid"]), "leaders")
    own = sets.select("rid").distinct().join(names, "rid", "left").select("rid", F.coalesce("leader", "rid").alias("grp"))
    own = materialize(own, "group-names")
    counts = own.groupBy("grp").agg(F.count(F.lit(1)).alias("_n"))
    own = hot_join(own, counts, "grp", "_n", own.count(), F.col("rid"))
    own = own.select("rid", "grp", F.pmod(F.xxhash64("rid"), F.ceil(F.col("_n") / block_rows)).cast("int").alias("part"))
    return sets.select("rid", "n", "tokens").join(own, "rid")


def matrix_links(sets: DataFrame, bucket_tokens: int = 1 << 20, share=SHARE, ask_rows: int = 512) -> DataFrame:
    """grp, other: groups with a verified link between a document of one and a member of the other."""
    total = sets.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    n_buckets = max(1, total // bucket_tokens + 1)

    def post(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            owners = [np.array([r, g], np.int64).tobytes() for r, g in zip(b.column("rid").to_pylist(), b.column("grp").to_pylist(), strict=True)]
            tokens = [np.frombuffer(x, _U) for x in b.column("tokens").to_pylist()]
            yield _blob_batch(list(_blobs(owners, tokens, n_buckets)))

    def spread(table: pa.Table) -> pa.Table:
        tokens, owners = _open_blobs(table, 16)
        order = np.lexsort((owners[:, 1], tokens))
        tokens, owners = tokens[order], owners[order]
        new_token = np.concatenate([[True], tokens[1:] != tokens[:-1]])
        new_group = new_token | np.concatenate([[True], owners[1:, 1] != owners[:-1, 1]])
        number = np.cumsum(new_token) - 1
        groups = np.bincount(number, weights=new_group).astype(np.int64)
        keep = groups[number] > 1
        return pa.table({"rid": owners[keep, 0], "token": tokens[keep].astype(np.int64), "groups": groups[number][keep]})

    held = sets.select("rid", "grp", "tokens").mapInArrow(post, _BLOB).groupBy("bucket").applyInArrow(spread, "rid long, token long, groups long")
    # tokens of no other group come first in the order; if they fill the prefix, the document is done
    by_doc = held.groupBy("rid").agg(F.array_sort(F.collect_list(F.struct("groups", "token"))).alias("s"))
    by_doc = by_doc.join(sets.select("rid", "n", "grp", "part"), "rid")
    alone = F.col("n") - F.size("s")
    long = F.col("n") - F.ceil(F.col("n") * share[0] / share[1]) + 1 - alone
    short = F.col("n") - F.ceil(F.col("n") * 2 * share[0] / (share[0] + share[1])) + 1 - alone
    lead = by_doc.where(long > 0).select("rid", "n", "grp", "part", short.alias("short"), F.size("s").alias("rest"), F.posexplode(F.slice("s", F.lit(1), long.cast("int"))).alias("at", "t"))
    # rest: how many tokens, this one included, can still be shared; the first shared token of a linked pair has enough on both sides
    lead = lead.select("rid", "n", "grp", "part", (F.col("at") < F.col("short")).alias("in_short"), (F.col("rest") - F.col("at")).alias("rest"), F.col("t.token").alias("token"))
    lead = materialize(lead, "prefixes")

    # the token-group matrix, by token: blocks whose members have it in their prefix, with their sizes
    matrix = lead.groupBy("token", F.col("grp").alias("m_grp"), F.col("part").alias("m_part")).agg(F.min("n").alias("m_min"), F.max("n").alias("m_max"), F.max("rest").alias("m_rest"))
    # the smaller document of a pair asks: partners have at least its size, so it needs that overlap
    partner = F.greatest(F.col("m_min"), F.col("n"))
    enough = F.least("rest", "m_rest") >= F.ceil((F.col("n") + partner) * share[0] / (share[0] + share[1]))
    sized = (F.col("m_max") >= F.col("n")) & (F.col("n") * share[1] >= F.col("m_min") * share[0])
    asks = lead.where("in_short").join(matrix, "token").where(enough & sized & (F.col("grp") != F.col("m_grp"))).select("rid", "m_grp", "m_part").distinct()
    asks = materialize(asks, "asks")

    # the unions of the blocks that are asked, one row each
    stored = materialize(_members(sets, asks).repartition("m_grp", "m_part").sortWithinPartitions("m_grp", "m_part").mapInArrow(_unions, "m_grp long, m_part int, least long, tokens binary"), "unions")
    qualified = materialize(_meet(stored, asks, sets, ask_rows).mapInArrow(_bounded, "rid long, m_grp long, m_part int"), "qualified")
    opened = _members(sets, qualified).select("m_grp", "m_part", F.lit(0).cast("long").alias("least"), "tokens")
    return _meet(opened, qualified, sets, ask_rows).mapInArrow(_opened, "grp long, other long").distinct()


def _members(sets: DataFrame, asks: DataFrame) -> DataFrame:
    """m_grp, m_part, tokens of the members of blocks that are asked."""
    blocks = asks.select("m_grp", "m_part").distinct()
    return sets.select(F.col("grp").alias("m_grp"), F.col("part").alias("m_part"), "tokens").join(blocks, ["m_grp", "m_part"], "left_semi")


def _meet(stored: DataFrame, asks: DataFrame, sets: DataFrame, ask_rows: int) -> DataFrame:
    """Rows of blocks (kind 0), then of documents that ask them (kind 1), side by side. Blocks with many askers are sent to several tasks, with a share of the askers each."""
    most = max(ask_rows, -(-asks.count() // HOT_PARTS))
    busy = asks.groupBy("m_grp", "m_part").agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") > most).select("m_grp", "m_part", F.ceil(F.col("_n") / most).cast("int").alias("splits"))
    busy = materialize(busy, "busy-blocks")  # at most HOT_PARTS rows
    n = F.coalesce("splits", F.lit(1))
    one = stored.join(F.broadcast(busy), ["m_grp", "m_part"], "left").select("m_grp", "m_part", F.explode(F.sequence(F.lit(0), n - 1)).alias("split"), F.lit(0).alias("kind"), "least", F.lit(None).cast("long").alias("rid"), F.lit(None).cast("long").alias("grp"), "tokens")
    split = F.pmod(F.xxhash64("rid"), n).cast("int").alias("split")
    two = asks.join(F.broadcast(busy), ["m_grp", "m_part"], "left").select("rid", "m_grp", "m_part", split).join(sets.select("rid", "grp", "tokens"), "rid")
    two = two.select("m_grp", "m_part", "split", F.lit(1).alias("kind"), F.lit(0).cast("long").alias("least"), "rid", "grp", "tokens")
    return one.unionByName(two).repartition("m_grp", "m_part", "split").sortWithinPartitions("m_grp", "m_part", "split", "kind")


def _unions(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row per block: the union of its members' tokens and the least size of a member. Rows of a block stand together."""
    at, members = None, []

    def row() -> pa.RecordBatch:
        union = np.unique(np.concatenate(members))
        cols = [pa.array([at[0]], pa.int64()), pa.array([at[1]], pa.int32()), pa.array([min(map(len, members))], pa.int64()), pa.array([union.tobytes()], pa.binary())]
        return pa.RecordBatch.from_arrays(cols, ["m_grp", "m_part", "least", "tokens"])

    for b in batches:
        for g, p, blob in zip(*(b.column(c).to_pylist() for c in ("m_grp", "m_part", "tokens")), strict=True):
            if (g, p) != at:
                if members:
                    yield row()
                at, members = (g, p), []
            members.append(np.frombuffer(blob, _U))
    if members:
        yield row()


_FACE = ("m_grp", "m_part", "split", "kind", "least", "rid", "grp", "tokens")


def _bounded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of documents and blocks those whose overlap with the union reaches what a link with some member needs."""
    union, least = None, 0
    for b in batches:
        out = []
        for g, p, _, kind, small, rid, _, blob in zip(*(b.column(c).to_pylist() for c in _FACE), strict=True):
            s = np.frombuffer(blob, _U)
            if not kind:
                union, least = s, small
                continue
            where = np.searchsorted(union, s)
            where[where == len(union)] = 0
            if int(np.count_nonzero(union[where] == s)) >= pair_overlap(len(s), max(least, len(s))):
                out.append((rid, g, p))
        cols = list(zip(*out, strict=True)) or [(), (), ()]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int32()), strict=True)], ["rid", "m_grp", "m_part"])


def _opened(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Groups with a verified link: the members of a qualified block against the documents that qualified."""
    at, members, done = None, [], set()
    for b in batches:
        out: set[tuple[int, int]] = set()
        for g, p, split, kind, _, _, own, blob in zip(*(b.column(c).to_pylist() for c in _FACE), strict=True):
            if (g, p, split) != at:
                at, members, done = (g, p, split), [], set()
            s = np.frombuffer(blob, _U)
            if not kind:
                members.append(s)
            elif own not in done and any(len(m) >= len(s) and linked(s, m) for m in members):  # else these two groups are joined already
                done.add(own)
                out.add((min(g, own), max(g, own)))
        yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in out], pa.int64()), pa.array([x[1] for x in out], pa.int64())], ["grp", "other"])


def components(links: DataFrame, a: str = "grp", b: str = "other") -> DataFrame:
    """node, root (least node that can be reached) of every node of a link. Each round takes over the least label around and jumps along labels."""
    both = materialize(links.select(F.col(a).alias("x"), F.col(b).alias("y")).union(links.select(F.col(b), F.col(a))).distinct(), "links")
    labels = materialize(both.groupBy(F.col("x").alias("node")).agg(F.least(F.min("y"), F.col("x")).alias("root")), "labels")
    while True:
        around = both.join(labels, F.col("y") == F.col("node")).groupBy("x").agg(F.min("root").alias("near"))
        lower = labels.join(around, F.col("node") == F.col("x"), "left").select("node", "root", F.least("root", "near").alias("next"))
        jump = labels.select(F.col("node").alias("_n"), F.col("root").alias("_r"))
        new = lower.join(jump, F.col("next") == F.col("_n"), "left").select("node", F.coalesce("_r", "next").alias("next"), "root")
        new = materialize(new.select("node", F.least("next", "root").alias("root"), (F.least("next", "root") != F.col("root")).alias("moved")), "labels")
        if not new.where("moved").limit(1).count():
            return new.select("node", "root")
        labels = new.select("node", "root")


def jaccard_components(docs: DataFrame, size: int = 5, id_col: str = "doc_id", text_col: str = "text", **grouping) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (least doc_id of its component), copies (documents with an equal set).

    grouping: options of :func:`grouped`; they change the work, never the result.
    """
    members = materialize(members_of(docs, size, id_col, text_col), "members")
    classes = members.where(F.col("digest").isNotNull()).groupBy("digest").agg(F.min("doc_id").alias("rid"), F.first("n_shingles").alias("n"), F.count(F.lit(1)).alias("copies"))
    classes = materialize(classes, "classes")
    total = classes.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum("copies"), F.lit(0))).first()
    survivors = materialize(prune(docs, classes.where(F.col("rid").isNotNull()), total[0], size, id_col, text_col), "survivors")
    n_survivors = survivors.count()
    # two rows may bear the id of a class; the least set of that size will do, as equal ids are one document
    sets = materialize(survivor_sets(docs, survivors, n_survivors, size, id_col, text_col), "sets")
    sets = materialize(grouped(sets, **grouping), "grouped-sets")
    links = materialize(matrix_links(sets), "matrix-links")
    roots = components(links)
    groups = sets.select("rid", "grp").join(roots, F.col("grp") == F.col("node"), "left").select("rid", F.coalesce("root", "grp").alias("top"))
    groups = materialize(groups, "tops")
    tops = groups.groupBy("top").agg(F.min("rid").alias("least"), F.count(F.lit(1)).alias("_n"))
    labels = hot_join(groups, tops, "top", "_n", n_survivors, F.col("rid")).select("rid", "least").dropDuplicates(["rid"])
    named = classes.join(labels, "rid", "left").select("digest", F.coalesce("least", "rid").alias("component_id"), "copies")
    out = hot_join(members, named, "digest", "copies", total[1], F.unhex(F.sha2(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), 256)))
    own = F.when(F.col("digest").isNull(), F.col("doc_id")).otherwise(F.col("component_id"))
    return out.select("doc_id", "n_shingles", own.alias("component_id"), F.coalesce("copies", F.lit(0)).alias("copies"))


def drop_near_copies(docs: DataFrame, size: int = 5, broadcast_rows: int = 300_000) -> DataFrame:
    """Of each component the document with the least doc_id stays, with all its columns."""
    found = materialize(jaccard_components(docs, size), "components")
    gone = found.where(F.col("doc_id") != F.col("component_id")).select("doc_id").distinct()
    gone = F.broadcast(gone) if gone.count() <= broadcast_rows else gone
    return docs.join(gone, "doc_id", "left_anti")
