"""Similarities as column expressions; Arrow functions only where Spark has no built-in.

Null policy: a null or empty side gives 0. What both sides lack is dropped from the
weighted similarity (``pair_similarity`` with ``drop_missing``).
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: The tokenizer of all workloads: runs of letters and digits, lower-cased.
TOKEN_SPLIT = r"[^\p{L}\p{N}]+"


def tokens(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), TOKEN_SPLIT), lambda x: x != "")


def first_tokens(text: Column, n: int) -> Column:
    """The first n tokens, without splitting what is behind them: only the first part of a split can be empty, so n of the first n + 1 parts are tokens where there are so many."""
    parts = F.split(F.lower(F.coalesce(text, F.lit(""))), TOKEN_SPLIT, n + 2)
    return F.slice(F.filter(F.slice(parts, 1, n + 1), lambda x: x != ""), 1, n)


def _ratio(a: Column, b: Column) -> Column:
    return F.coalesce(F.try_divide(a.cast("double"), b.cast("double")), F.lit(0.0))


def jaccard(a: Column, b: Column) -> Column:
    a, b = F.coalesce(a, F.array().cast("array<string>")), F.coalesce(b, F.array().cast("array<string>"))
    return _ratio(F.size(F.array_intersect(a, b)), F.size(F.array_union(a, b)))


def containment(a: Column, b: Column) -> Column:
    """Share of a's tokens that b has."""
    return _ratio(F.size(F.array_intersect(a, b)), F.size(F.array_distinct(a)))


def edit_sim(a: Column, b: Column) -> Column:
    a, b = F.coalesce(a, F.lit("")), F.coalesce(b, F.lit(""))
    longest = F.greatest(F.length(a), F.length(b))
    return F.when((F.length(a) == 0) | (F.length(b) == 0), 0.0).otherwise(1 - _ratio(F.levenshtein(a, b), longest))


def number_sim(a: Column, b: Column, tol: float = 1.0) -> Column:
    a, b = a.cast("double"), b.cast("double")
    scale = F.greatest(F.abs(a), F.abs(b)) * tol
    near = F.greatest(F.lit(0.0), 1 - _ratio(F.abs(a - b), scale))
    return F.when(a.isNull() | b.isNull(), 0.0).when(a == b, 1.0).otherwise(near)


def exact_sim(a: Column, b: Column) -> Column:
    return F.when(a.isNull() | b.isNull(), 0.0).otherwise((a == b).cast("double"))


def hybrid(a: Column, b: Column, mode: str = "mean") -> Column:
    """Of two token arrays: mean or greater of Jaccard and edit similarity."""
    set_part, text_part = jaccard(a, b), edit_sim(F.array_join(a, " "), F.array_join(b, " "))
    return (set_part + text_part) / 2 if mode == "mean" else F.greatest(set_part, text_part)


def soft_jaccard(a: Column, b: Column, least: float = 0.8) -> Column:
    """Jaccard in which a token also meets a token of at least this edit similarity."""
    a, b = F.array_distinct(a), F.array_distinct(b)
    met = F.size(F.filter(a, lambda x: F.exists(b, lambda y: edit_sim(x, y) >= least)))
    return _ratio(met, F.size(a) + F.size(b) - met)


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q), F.lit(0.0), lambda s, v: s + v)
    return _ratio(dot(a, b), F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def jaro_value(a: str, b: str) -> float:
    if not a or not b:
        return 0.0
    if a == b:
        return 1.0
    reach = max(max(len(a), len(b)) // 2 - 1, 0)
    used = [False] * len(b)
    hits = []
    for i, c in enumerate(a):
        for j in range(max(0, i - reach), min(len(b), i + reach + 1)):
            if not used[j] and b[j] == c:
                used[j] = True
                hits.append(c)
                break
    if not hits:
        return 0.0
    others = [c for j, c in enumerate(b) if used[j]]
    swaps = sum(x != y for x, y in zip(hits, others, strict=True)) // 2
    m = len(hits)
    return (m / len(a) + m / len(b) + (m - swaps) / m) / 3


def jaro_winkler_value(a: str, b: str, scale: float = 0.1, boost_from: float = 0.7) -> float:
    j = jaro_value(a, b)
    if j <= boost_from:
        return j
    n = 0
    for x, y in zip(a[:4], b[:4], strict=False):
        if x != y:
            break
        n += 1
    return j + n * scale * (1 - j)


def _pairwise(f, a: pd.Series, b: pd.Series) -> pd.Series:
    known: dict[tuple, float] = {}
    out = np.empty(len(a))
    for k, p in enumerate(zip(a, b, strict=True)):
        if p not in known:
            known[p] = f(p[0] or "", p[1] or "")
        out[k] = known[p]
    return pd.Series(out)


@F.pandas_udf(T.DoubleType())
def jaro(a: pd.Series, b: pd.Series) -> pd.Series:
    return _pairwise(jaro_value, a, b)


@F.pandas_udf(T.DoubleType())
def jaro_winkler(a: pd.Series, b: pd.Series) -> pd.Series:
    return _pairwise(jaro_winkler_value, a, b)


def lcs_tokens(a: Column, b: Column) -> Column:
    """Length of the longest run of consecutive tokens that both have: rolling rows of the usual table, on the JVM."""
    zero = F.struct(F.array_repeat(F.lit(0), F.size(b)).alias("row"), F.lit(0).alias("best"))

    def step(acc: Column, x: Column) -> Column:
        row = F.transform(b, lambda y, j: F.when(x == y, F.when(j > 0, F.get(acc["row"], j - 1)).otherwise(0) + 1).otherwise(0))
        return F.struct(row.alias("row"), F.greatest(acc["best"], F.coalesce(F.array_max(row), F.lit(0))).alias("best"))

    return F.aggregate(a, zero, step)["best"]


def lcs_share(a: Column, b: Column) -> Column:
    return _ratio(lcs_tokens(a, b), F.least(F.size(a), F.size(b)))


def lcs_run_value(a: np.ndarray, b: np.ndarray) -> int:
    """Length of the longest run of consecutive tokens that both have; a row of the table at a time, so memory is that of the longer text."""
    if len(a) > len(b):
        a, b = b, a
    both = set(a.tolist()) & set(b.tolist())
    if not both:
        return 0
    code = {t: k for k, t in enumerate(both, 1)}
    long = np.array([code.get(t, -1) for t in b.tolist()], dtype=np.int64)
    places: dict[int, np.ndarray] = {}
    row, best = np.zeros(len(long) + 1, dtype=np.int64), 0
    touched = np.zeros(0, dtype=np.int64)
    for t in a.tolist():
        c = code.get(t)
        if c is None:
            row[touched] = 0
            touched = touched[:0]
            continue
        if c not in places:
            places[c] = np.nonzero(long == c)[0]
        at = places[c]
        runs = row[at] + 1
        row[touched] = 0
        row[at + 1] = runs
        touched = at + 1
        best = max(best, int(runs.max()))
    return best


@F.pandas_udf(T.DoubleType())
def lcs_share_long(a: pd.Series, b: pd.Series) -> pd.Series:
    """The longest common run over the shorter side's length, for long texts: work grows with the places at which tokens meet."""
    empty = np.zeros(0, dtype=object)
    out = []
    for x, y in zip(a, b, strict=True):
        x, y = (empty if v is None else np.asarray(v, dtype=object) for v in (x, y))
        out.append(lcs_run_value(x, y) / min(len(x), len(y)) if len(x) and len(y) else 0.0)
    return pd.Series(out, dtype=float)


def weighted_similarity(parts: dict[str, float], drop_missing: bool = False) -> Column:
    """Weighted mean of the named columns; drop_missing leaves out nulls and their weights."""
    if not drop_missing:
        total = sum(parts.values())
        out = F.lit(0.0)
        for c, w in parts.items():
            out = out + F.coalesce(F.col(c), F.lit(0.0)) * (w / total)
        return out
    top, low = F.lit(0.0), F.lit(0.0)
    for c, w in parts.items():
        top = top + F.coalesce(F.col(c) * w, F.lit(0.0))
        low = low + F.when(F.col(c).isNull(), 0.0).otherwise(w)
    return _ratio(top, low)
