"""Toxicity: cumulative-link ordinal regression on sparse text features.

Severity grades are 0 (not toxic) to 3. The labels tell toxic from clean; among
toxic documents the share of words that go with toxicity, cut into thirds, gives
the grade. One weight vector serves all ordered thresholds: P(grade > k) is the
logistic of score - threshold[k], and the expected severity is the sum of these.

Features are the distinct words of a text and their first 5, 6 and 7 letters. The
model is fitted on a bounded sample of labelled rows (``max_labels``, in hash
order) and has at most ``max_features`` features, picked by their association with
the label; so what is broadcast has a fixed bound. The cutoff that rejects a
document is chosen on a fifth of the sample that was held out. Every document is
then scored over its whole text.

Defined results: null and empty texts have the severity of a text without any
feature; a document labelled more than once counts as toxic if any label says so;
without labels of both classes every severity is 0 and nothing is rejected;
repeated rows are scored alike; an empty table gives an empty result; columns
other than the named ones play no part.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize

GRADES = 4
_WORD = re.compile(r"[^\W\d_]+")
PREFIXES = (5, 6, 7)


def words_of(text: str | None) -> list[str]:
    return _WORD.findall((text or "").lower())


def features_of(word: str) -> list[str]:
    return [word, *(f"{word[:n]}*" for n in PREFIXES if len(word) > n)]


@dataclass
class OrdinalModel:
    weights: dict[str, float] = field(default_factory=dict)
    thresholds: tuple[float, ...] = ()
    cutoff: float = float("inf")
    held_out: dict[str, float] = field(default_factory=dict)

    def word_score(self, word: str) -> float:
        return sum(self.weights.get(f, 0.0) for f in features_of(word))

    def severity(self, score: np.ndarray) -> np.ndarray:
        if not self.thresholds:
            return np.zeros(len(score))
        return (1 / (1 + np.exp(-np.clip(score[:, None] - np.array(self.thresholds), -60, 60)))).sum(axis=1)


def fit_ordinal(rows: list[np.ndarray], grades: np.ndarray, n_features: int, l2: float = 1e-3, rounds: int = 400, rate: float = 0.05) -> tuple[np.ndarray, np.ndarray]:
    """Weights and ordered thresholds by maximum likelihood; rows hold feature numbers (repeats count)."""
    at = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
    cols = np.concatenate([*rows, np.zeros(0, dtype=np.int64)]).astype(np.int64)
    n, top = len(rows), GRADES - 1
    share = [np.clip((grades > k).mean(), 1e-3, 1 - 1e-3) for k in range(top)]
    start = np.maximum.accumulate([-np.log(p / (1 - p)) for p in share])
    par = np.concatenate([np.zeros(n_features), [start[0]], np.log(np.maximum(np.diff(start), 0.05))])
    m1, m2 = np.zeros_like(par), np.zeros_like(par)
    sig = lambda z: 1 / (1 + np.exp(-np.clip(z, -60, 60)))
    for step in range(1, rounds + 1):
        w, gaps = par[:n_features], np.exp(par[n_features + 1 :])
        theta = par[n_features] + np.concatenate([[0.0], np.cumsum(gaps)])
        s = np.bincount(at, w[cols], minlength=n)
        cdf = np.column_stack([np.zeros(n), sig(theta - s[:, None]), np.ones(n)])
        lo, hi = cdf[np.arange(n), grades], cdf[np.arange(n), grades + 1]
        p = np.maximum(hi - lo, 1e-12)
        d_hi, d_lo = hi * (1 - hi) / p, lo * (1 - lo) / p
        g_s = (d_hi - d_lo) / n  # of the negative log-likelihood
        g_w = np.bincount(cols, g_s[at], minlength=n_features) + l2 * w
        g_t = np.zeros(top)
        for k in range(top):
            g_t[k] = (-d_hi[grades == k].sum() + d_lo[grades == k + 1].sum()) / n
        g = np.concatenate([g_w, [g_t.sum()], gaps * np.cumsum(g_t[::-1])[::-1][1:]])
        m1, m2 = 0.9 * m1 + 0.1 * g, 0.999 * m2 + 0.001 * g * g
        par = par - rate * (m1 / (1 - 0.9**step)) / (np.sqrt(m2 / (1 - 0.999**step)) + 1e-9)
    gaps = np.exp(par[n_features + 1 :])
    return par[:n_features], par[n_features] + np.concatenate([[0.0], np.cumsum(gaps)])


def fit(docs: DataFrame, labels: DataFrame, max_labels: int = 10_000, max_features: int = 20_000, least_df: int = 5, least_z: float = 3.0, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> OrdinalModel:
    known = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("_i")).agg(F.max(F.col(label_col).cast("int")).alias("toxic"))
    known = known.orderBy(F.xxhash64("_i"), "_i").limit(max_labels)
    texts = docs.select(F.col(id_col).alias("_i"), F.col(text_col).alias("t")).join(F.broadcast(known), "_i")
    fold = F.pmod(F.xxhash64("_i", F.lit(1)), F.lit(5)).cast("int").alias("fold")

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            words = [words_of(x.as_py()) for x in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(words, pa.list_(pa.string()))], ["toxic", "fold", "words"])

    sample = materialize(texts.select("toxic", fold, "t").mapInArrow(split, "toxic int, fold int, words array<string>"), "toxic-sample")

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            all_, bad = Counter(), Counter()
            for y, f, words in zip(*(b.column(c).to_pylist() for c in ("toxic", "fold", "words")), strict=True):
                if f:  # fold 0 is held out
                    own = {x for w in set(words) for x in features_of(w)}
                    all_.update(own)
                    if y:
                        bad.update(own)
            names = list(all_)
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array([all_[x] for x in names], pa.int64()), pa.array([bad[x] for x in names], pa.int64())], ["f", "n", "y"])

    sums = {(r["toxic"], r["held"]): r["n"] for r in sample.groupBy("toxic", (F.col("fold") == 0).alias("held")).agg(F.count(F.lit(1)).alias("n")).collect()}
    n1, n0 = sums.get((1, False), 0), sums.get((0, False), 0)
    if not n0 or not n1:
        return OrdinalModel()
    base = n1 / (n0 + n1)
    df = sample.mapInArrow(counted, "f string, n long, y long").groupBy("f").agg(F.sum("n").alias("n"), F.sum("y").alias("y")).where(F.col("n") >= least_df)
    df = df.withColumn("z", (F.col("y") - F.col("n") * base) / F.sqrt(F.col("n") * (base * (1 - base))))
    picked = df.where(F.abs("z") >= least_z).orderBy(F.desc(F.abs("z")), "f").limit(max_features).collect()
    number = {r["f"]: k for k, r in enumerate(picked)}
    strong = {r["f"] for r in picked if r["z"] > 0 and r["y"] >= 0.8 * r["n"]}
    chosen = sample.sparkSession.sparkContext.broadcast((number, strong))

    def coded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known_, strong_ = chosen.value
        for b in batches:
            cols: list[list] = [[], []]
            for words in b.column("words").to_pylist():
                cols[0].append([known_[x] for w in set(words) for x in features_of(w) if x in known_])
                cols[1].append(sum(not strong_.isdisjoint(features_of(w)) for w in words) / max(1, len(words)))
            yield pa.RecordBatch.from_arrays([b.column("toxic"), b.column("fold"), pa.array(cols[0], pa.list_(pa.int32())), pa.array(cols[1], pa.float64())], ["toxic", "fold", "x", "share"])

    data = sample.mapInArrow(coded, "toxic int, fold int, x array<int>, share double").toPandas()  # at most max_labels rows
    y = data["toxic"].to_numpy()
    toxic_share = data.loc[(y > 0) & (data["fold"] > 0), "share"]
    cuts = np.quantile(toxic_share, [1 / 3, 2 / 3])
    grades = np.where(y > 0, 1 + (data["share"].to_numpy()[:, None] > cuts).sum(axis=1), 0)
    rows = [np.asarray(x, dtype=np.int64) for x in data["x"]]
    train = (data["fold"] > 0).to_numpy()
    w, theta = fit_ordinal([r for r, t in zip(rows, train, strict=True) if t], grades[train], len(number))
    model = OrdinalModel({f: float(w[k]) for f, k in number.items() if abs(w[k]) > 1e-4}, tuple(theta.tolist()))
    # the cutoff with the best F1 on the held-out fold, or on all of a sample too small for one
    fold0 = ~train if (~train & (y > 0)).sum() >= 5 else np.ones(len(y), dtype=bool)
    severity = model.severity(np.array([w[r].sum() for r in rows])[fold0])
    truth = y[fold0] > 0
    best = (-1.0, 0.5)
    for c in np.arange(0.1, 2.0, 0.05):
        hit = severity >= c
        f1 = 2 * (hit & truth).sum() / max(1, hit.sum() + truth.sum())
        best = max(best, (f1, -abs(c - 0.5), c))  # ties: the one nearest to 0.5
    model.cutoff = float(best[-1])
    hit = severity >= model.cutoff
    model.held_out = {"precision": float((hit & truth).sum() / max(1, hit.sum())), "recall": float((hit & truth).sum() / max(1, truth.sum())), "f1": float(best[0])}
    return model


def severity_of(text: Column, model: OrdinalModel, spark, max_words: int = 200_000) -> Column:
    """Expected severity of a text as a column."""
    sent = spark.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def score(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        own = sent.value
        cache: dict[str, float] = {}
        for texts in batches:
            out = np.empty(len(texts))
            for i, t in enumerate(texts):
                words = set(words_of(t))
                try:
                    out[i] = sum(map(cache.__getitem__, words))
                except KeyError:
                    if len(cache) > max_words:
                        cache.clear()
                    for w in words:
                        if w not in cache:
                            cache[w] = own.word_score(w)
                    out[i] = sum(map(cache.__getitem__, words))
            yield pd.Series(own.severity(out))

    return score(text)


def grade(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """doc_id, severity (expected, 0 to 3), grade (nearest), toxic (severity at or over the cutoff)."""
    model = fit(docs, labels, id_col=id_col, text_col=text_col, **options)
    out = docs.select(F.col(id_col).alias("doc_id"), severity_of(F.col(text_col), model, docs.sparkSession).alias("severity"))
    return out.select("doc_id", "severity", F.round("severity").cast("int").alias("grade"), (F.col("severity") >= model.cutoff).alias("toxic"))


def drop_toxic(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """The documents that are not rejected, with all their columns."""
    model = fit(docs, labels, **options)
    return docs.where(severity_of(F.col("text"), model, docs.sparkSession) < model.cutoff)
