"""Nearest neighbours by largest inner product with a hierarchical k-means tree and best-bin-first traversal.

The tree is fitted on a bounded sample (``sample_rows``); it has a leaf for about
``leaf_rows`` rows, but at most ``max_leaves``, so what is broadcast has a fixed
bound; every row is then put into its leaf. A query walks the tree through a priority queue of nodes, by
the inner product with the centre plus the part of the query's norm that the
node's radius can add, and visits leaves in that order. How many leaves are
visited is calibrated: the true neighbours of a bounded number of queries are
found against all rows, and visits widen until the mean recall on these reaches
``target_recall``. A query whose leaves hold too few candidates goes on through its
queue until they hold enough.

Rows and queries meet in cells of bounded size: a group of leaves is split by row
id into cells of about ``cell_rows`` rows, so a very common vector is spread over
many cells, and the queries that ask for a group go in blocks of about
``query_rows``; a group's rows are sent once for each block that asks for them. Scores are exact, in
double precision, on the original vectors.

Defined results: vectors that are null, zero, of another length than most, or that
hold null or non-finite components take no part; equal scores go to the smaller
id; rows that repeat an id are candidates of their own, but never for a query of
that id; fewer candidates than asked for are all returned; an empty table gives an
empty result; columns other than the two named ones play no part.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize


@dataclass
class Tree:
    """Nodes in one table; children of node i are first[i] to first[i] + count[i] - 1; leaves have count 0."""

    centres: np.ndarray
    radius: np.ndarray
    first: np.ndarray
    count: np.ndarray
    leaf: np.ndarray  # leaf number or -1

    @property
    def n_leaves(self) -> int:
        return int(self.leaf.max()) + 1

    def assign(self, x: np.ndarray) -> np.ndarray:
        """The leaf of each row: the nearest child at each step."""
        node = np.zeros(len(x), dtype=np.int64)
        while (inner := self.count[node] > 0).any():
            for i in np.unique(node[inner]):
                own = np.nonzero(node == i)[0]
                kids = slice(self.first[i], self.first[i] + self.count[i])
                c = self.centres[kids]
                node[own] = self.first[i] + np.argmax(x[own] @ c.T - (c * c).sum(1) / 2, axis=1)
        return self.leaf[node]

    def order(self, q: np.ndarray, visits: int, rows: np.ndarray | None = None, least: int = 0) -> list[int]:
        """The first ``visits`` leaves in best-bin-first order, and further ones until they hold ``least`` rows; rows: of each leaf."""
        score = self.centres @ q + np.linalg.norm(q) * self.radius * 0.5
        heap, out, held = [(-score[0], 0)], [], 0
        while heap and (len(out) < visits or (rows is not None and held < least)):
            _, i = heapq.heappop(heap)
            if not self.count[i]:
                out.append(int(self.leaf[i]))
                held += int(rows[out[-1]]) if rows is not None else 0
            for k in range(self.first[i], self.first[i] + self.count[i]):
                heapq.heappush(heap, (-score[k], k))
        return out


def _kmeans(x: np.ndarray, k: int, rounds: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    centres = x[rng.choice(len(x), k, replace=False)].copy()
    near = np.zeros(len(x), dtype=np.int64)
    for _ in range(rounds):
        near = np.argmax(x @ centres.T - (centres * centres).sum(1) / 2, axis=1)
        for j in range(k):
            if (own := near == j).any():
                centres[j] = x[own].mean(0)
    return centres, near


def fit_tree(x: np.ndarray, leaves: int, branching: int = 8, rounds: int = 8, seed: int = 42) -> Tree:
    """Splits the node with most sample rows until there are so many leaves or nothing can be split."""
    rng = np.random.default_rng(seed)
    centres, radius, first, count = [x.mean(0)], [0.0], [0], [0]
    heap = [(-len(x), 0, np.arange(len(x)))]
    open_leaves = 1
    while heap and open_leaves + branching - 1 <= leaves:
        _, i, rows = heapq.heappop(heap)
        distinct = len(np.unique(x[rows], axis=0)) if len(rows) < 4096 else branching + 1
        k = min(branching, distinct)
        if k < 2:
            continue
        c, near = _kmeans(x[rows], k, rounds, rng)
        used = [j for j in range(k) if (near == j).any()]
        if len(used) < 2:
            continue
        first[i], count[i] = len(centres), len(used)
        open_leaves += len(used) - 1
        for j in used:
            own = rows[near == j]
            centres.append(c[j])
            radius.append(float(np.sqrt(((x[own] - c[j]) ** 2).sum(1).mean())))
            first.append(0)
            count.append(0)
            heapq.heappush(heap, (-len(own), len(centres) - 1, own))
    is_leaf = np.array(count) == 0
    leaf = np.where(is_leaf, np.cumsum(is_leaf) - 1, -1)
    return Tree(np.array(centres), np.array(radius), np.array(first), np.array(count), leaf)


def usable(v: Column) -> Column:
    sound = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.coalesce(v.isNotNull() & sound & F.exists(v, lambda x: x != 0), F.lit(False))


def _matrix(values) -> np.ndarray:
    return np.array([np.asarray(v, dtype=np.float64) for v in values])


def best(q_ids: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray, s: np.ndarray, k: int) -> pd.DataFrame:
    """The k best of each query by score, then id; s holds scores (-inf: not visited), which are taken again exactly for those near the k-th."""
    s = np.where(q_ids[:, None] == ids[None, :], -np.inf, s)
    kth = np.partition(s, -k, axis=1)[:, -k] if s.shape[1] > k else np.full(len(s), -np.inf)
    near = (s > -np.inf) & (s >= (kth - 1e-9 * (1 + np.abs(np.where(np.isinf(kth), 0, kth))))[:, None])
    a, b = np.nonzero(near)
    exact = np.empty(len(a))
    for at in range(0, len(a), 1 << 16):
        t = slice(at, at + (1 << 16))
        exact[t] = (q[a[t]] * x[b[t]]).sum(axis=1)
    order = np.lexsort((ids[b], -exact, a))
    a, b, exact = a[order], b[order], exact[order]
    place = np.arange(len(a)) - np.searchsorted(a, a, side="left")
    top = place < k
    return pd.DataFrame({"query_id": q_ids[a[top]], "vec_id": ids[b[top]], "score": exact[top]})


def nearest(
    vectors: DataFrame,
    is_query: Column,
    k: int = 20,
    id_col: str = "vec_id",
    vector_col: str = "embedding",
    target_recall: float = 0.96,
    sample_rows: int = 20_000,
    max_leaves: int = 1024,
    leaf_rows: int = 16,
    calibration_queries: int = 128,
    cell_rows: int = 16_384,
    query_rows: int = 4096,
    visits: int | None = None,
) -> DataFrame:
    """query_id, rank (from 1), vec_id, score, visits (leaves that each query opens, if they hold enough). is_query must be the same for rows of one id."""
    spark = vectors.sparkSession
    schema = "query_id long, rank int, vec_id long, score double, visits int"
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).alias("v"), is_query.alias("is_query")).where(usable(F.col("v")) & F.col("vec_id").isNotNull())
    sizes = rows.groupBy(F.size("v").alias("d")).agg(F.count(F.lit(1)).alias("n"), F.count_if("is_query").alias("q")).orderBy(F.desc("n"), "d").first()
    if sizes is None or not sizes["q"]:
        return spark.createDataFrame([], schema)
    rows = rows.where(F.size("v") == sizes["d"])
    n, n_queries = sizes["n"], sizes["q"]

    by_hash = F.xxhash64("vec_id")
    sample = rows.orderBy(by_hash, "vec_id").limit(sample_rows).select("v") if n > sample_rows else rows.select("v")
    x = _matrix(sample.toPandas()["v"])
    tree = fit_tree(x, max(1, min(max_leaves, n // leaf_rows)))
    leaves = tree.n_leaves
    shared = spark.sparkContext.broadcast(tree)

    def assigned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                leaf = shared.value.assign(_matrix(b.column("v").to_pylist()))
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(leaf, pa.int32())], [*b.schema.names, "leaf"])

    element = rows.schema["v"].dataType.simpleString()
    index = materialize(rows.mapInArrow(assigned, f"vec_id long, v {element}, is_query boolean, leaf int"), "vector-index")

    if visits is None:
        visits = _calibrate(index, tree, k, calibration_queries, target_recall)

    # groups of neighbouring leaves, split into cells of bounded size
    counts = {r["leaf"]: r["n"] for r in index.groupBy("leaf").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most max_leaves rows
    in_leaf = np.array([counts.get(leaf, 0) for leaf in range(leaves)])
    same = index.where("is_query").groupBy("vec_id").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0]  # rows of one id are no candidates of each other
    group_of, cells_of, group, held = {}, [], 0, 0
    for leaf in range(leaves):
        group_of[leaf] = group
        held += counts.get(leaf, 0)
        if held >= cell_rows or leaf == leaves - 1:
            cells_of.append(max(1, -(-held // cell_rows)))
            group, held = group + 1, 0
    groups = np.array([group_of[i] for i in range(leaves)])

    def visiting(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = {"query_id": [], "q": [], "grp": [], "leaves": []}
            for i, v in zip(b.column("vec_id").to_pylist(), b.column("v").to_pylist(), strict=True):
                order = np.array(shared.value.order(np.asarray(v, dtype=np.float64), visits, in_leaf, k + same))
                of = groups[order]
                for g in np.unique(of).tolist():
                    for name, value in zip(out, (i, v, g, order[of == g].tolist()), strict=True):
                        out[name].append(value)
            types = [pa.int64(), b.schema.field("v").type, pa.int32(), pa.list_(pa.int32())]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out.values(), types, strict=True)], list(out))

    asked_for = materialize(index.where("is_query").select("vec_id", "v").mapInArrow(visiting, f"query_id long, q {element}, grp int, leaves array<int>"), "visits")
    askers = {r["grp"]: r["n"] for r in asked_for.groupBy("grp").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most max_leaves rows
    blocks_of = [-(-askers.get(g, 0) // query_rows) for g in range(len(cells_of))]
    numbers = lambda values: F.array(*[F.lit(int(x)) for x in values])
    upto = lambda n: F.explode(F.sequence(F.lit(0), n - 1))
    block = F.pmod(F.xxhash64("query_id"), F.get(numbers(blocks_of), F.col("grp"))).cast("int")
    queries = asked_for.select("query_id", "q", "grp", block.alias("block"), "leaves", upto(F.get(numbers(cells_of), F.col("grp"))).alias("salt"))
    cells = index.withColumn("grp", F.get(numbers(groups), F.col("leaf")))
    cells = cells.withColumn("salt", F.pmod(by_hash, F.get(numbers(cells_of), F.col("grp"))).cast("int")).withColumn("blocks", F.get(numbers(blocks_of), F.col("grp")))
    cells = cells.where("blocks > 0").select("grp", "salt", upto(F.col("blocks")).alias("block"), "vec_id", "v", "leaf")

    def search(data: pd.DataFrame, asked: pd.DataFrame) -> pd.DataFrame:
        if data.empty or asked.empty:
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []})
        data = data.sort_values("leaf", kind="stable")
        ids, vs, leaf = data["vec_id"].to_numpy(), _matrix(data["v"]), data["leaf"].to_numpy()
        q_ids, qs = asked["query_id"].to_numpy(), _matrix(asked["q"])
        seen = np.zeros((len(asked), leaves), dtype=bool)
        for r, own in enumerate(asked["leaves"]):
            seen[r, own] = True
        starts = {v: (a, b) for v in np.unique(leaf) for a, b in [np.searchsorted(leaf, [v, v + 1])]}
        found = []
        step = max(1, (1 << 22) // len(ids))
        for at in range(0, len(q_ids), step):
            part = slice(at, at + step)
            s = np.full((len(q_ids[part]), len(ids)), -np.inf)
            for v, (a, b) in starts.items():
                own = np.nonzero(seen[part, v])[0]
                if len(own):
                    s[own, a:b] = qs[part][own] @ vs[a:b].T
            found.append(best(q_ids[part], qs[part], ids, vs, s, k))
        return pd.concat(found)

    keys = ["grp", "salt", "block"]
    met = cells.groupBy(*keys).cogroup(queries.groupBy(*keys)).applyInPandas(search, "query_id long, vec_id long, score double")
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return met.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score", F.lit(visits).alias("visits"))


def _calibrate(index: DataFrame, tree: Tree, k: int, n_queries: int, target: float) -> int:
    """The least number of leaf visits at which the mean recall of a bounded set of queries, whose true neighbours are found against all rows, reaches the target."""
    asked = index.where("is_query").orderBy(F.xxhash64("vec_id"), "vec_id").limit(n_queries).select("vec_id", "v").toPandas()
    q_ids, qs = asked["vec_id"].to_numpy(), _matrix(asked["v"])
    sent = index.sparkSession.sparkContext.broadcast((q_ids, qs))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        i, q = sent.value
        held = None
        for b in batches:
            ids, x, leaf = b.column("vec_id").to_numpy(), _matrix(b.column("v").to_pylist()), b.column("leaf").to_numpy()
            if not len(ids):
                continue
            # row numbers stand for ids, so that the leaf of each can be told
            top = best(i, q, ids, x, q @ x.T, k)
            where = dict(zip(ids.tolist(), leaf.tolist(), strict=True))
            top["leaf"] = [where[v] for v in top["vec_id"]]
            held = top if held is None else pd.concat([held, top]).sort_values(["score", "vec_id"], ascending=[False, True]).groupby("query_id").head(k)
        if held is not None:
            yield pa.RecordBatch.from_pandas(held[["query_id", "vec_id", "score", "leaf"]].astype({"leaf": "int32"}), preserve_index=False)

    met = index.select("vec_id", "v", "leaf").mapInArrow(scan, "query_id long, vec_id long, score double, leaf int")
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    truth = met.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).toPandas()  # at most n_queries * k rows
    if truth.empty:
        return 1
    at = {i: {leaf: r for r, leaf in enumerate(tree.order(q, tree.n_leaves))} for i, q in zip(q_ids.tolist(), qs, strict=True)}
    needed = np.array([at[i][leaf] for i, leaf in zip(truth["query_id"].tolist(), truth["leaf"].tolist(), strict=True)])
    total = len(needed)
    for visits in range(1, tree.n_leaves + 1):
        if (needed < visits).sum() >= target * total:
            return visits
    return tree.n_leaves
