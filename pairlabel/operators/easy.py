"""Labels of the easy pairs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def easy_by_bounds(pairs: DataFrame, lo: float, hi: float, metric: str = "sim") -> DataFrame:
    """pair_id, label: match at or over hi, non-match at or under lo; others have no row."""
    label = F.when(F.col(metric) >= hi, 1).when(F.col(metric) <= lo, 0)
    return pairs.select("pair_id", label.alias("label")).where(F.col("label").isNotNull())


def extremes(pairs: DataFrame, n_match: int, n_nonmatch: int, metric: str = "sim", grain: int = 1000) -> DataFrame:
    """The n_match most and n_nonmatch least similar pairs; ties by pair_id.

    Only the boundary buckets are ranked: counts per similarity bucket (at most grain
    rows) tell which buckets lie wholly inside, so no window sees all pairs.
    """
    bucket = F.least(F.floor(F.col(metric) * grain), F.lit(grain - 1)).cast("int")
    rows = pairs.select("pair_id", F.col(metric).alias("v"), bucket.alias("b"))
    counts = sorted((r["b"], r["n"]) for r in rows.groupBy("b").agg(F.count(F.lit(1)).alias("n")).collect())

    def edge(order: list[tuple[int, int]], want: int) -> tuple[int | None, int]:
        """The bucket in which the cut falls, and how many of it are taken."""
        for b, n in order:
            if want <= n:
                return b, want
            want -= n
        return None, 0

    top, take_top = edge(counts[::-1], n_match)
    low, take_low = edge(counts, n_nonmatch)
    over = rows.where(F.col("b") > top) if top is not None else rows
    under = rows.where(F.col("b") < low) if low is not None else rows
    out = over.select("pair_id", F.lit(1).alias("label")).unionAll(under.select("pair_id", F.lit(0).alias("label")))
    for b, take, label, order in ((top, take_top, 1, F.desc("v")), (low, take_low, 0, F.asc("v"))):
        if take:
            out = out.unionAll(rows.where(F.col("b") == b).orderBy(order, "pair_id").limit(take).select("pair_id", F.lit(label).alias("label")))
    return out


def easy_by_ratio(pairs: DataFrame, ratio: float, share: float, metric: str = "sim") -> DataFrame:
    """Of n pairs the floor(ratio n share) most similar are matches, the floor(ratio n (1 - share)) least similar non-matches."""
    n = pairs.count()
    return extremes(pairs, int(ratio * n * share + 1e-9), int(ratio * n * (1 - share) + 1e-9), metric)


def easy_by_center(pairs: DataFrame, centres: list[dict[str, float]], ratio: float) -> DataFrame:
    """The share of each cluster that lies nearest to its centre; the cluster with the higher centre is match."""
    cols = list(centres[0])
    order = sorted(range(2), key=lambda k: sum(centres[k].values()))
    dist = [sum(((F.col(c) - centres[k][c]) ** 2 for c in cols), F.lit(0.0)) for k in order]
    rows = pairs.select("pair_id", (dist[1] < dist[0]).cast("int").alias("label"), F.least(*dist).alias("d"))
    w = Window.partitionBy("label").orderBy("d", "pair_id")
    n = F.count(F.lit(1)).over(Window.partitionBy("label"))
    ranked = rows.withColumn("r", F.row_number().over(w)).withColumn("n", n)
    return ranked.where(F.col("r") <= F.floor(F.col("n") * ratio)).select("pair_id", "label")


def easy_by_rules(pairs: DataFrame, rules: list[tuple[str, int]]) -> DataFrame:
    """SQL predicates with a label; the first that holds decides."""
    label: Column = F.lit(None).cast("int")
    for predicate, value in reversed(rules):
        label = F.when(F.expr(predicate), value).otherwise(label)
    return pairs.select("pair_id", label.alias("label")).where(F.col("label").isNotNull())


def easy_accuracy(pairs: DataFrame, truth: DataFrame, ratios: list[float], share: float) -> DataFrame:
    """Accuracy of both kinds of easy labels by ratio."""
    out = None
    for ratio in ratios:
        rows = easy_by_ratio(pairs, ratio, share).join(truth, "pair_id")
        one = rows.agg(
            F.lit(ratio).alias("ratio"),
            (F.count_if(F.expr("label = 1 and truth = 1")) / F.greatest(F.count_if(F.expr("label = 1")), F.lit(1))).alias("match_accuracy"),
            (F.count_if(F.expr("label = 0 and truth = 0")) / F.greatest(F.count_if(F.expr("label = 0")), F.lit(1))).alias("nonmatch_accuracy"),
        )
        out = one if out is None else out.unionAll(one)
    return out
