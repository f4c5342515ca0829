"""One round of inference as DataFrame operators: statistics, curves, confidence, support, approximation, subgraph."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import influence as I
from ..settings import Settings
from .workload import hash_order


def class_weight(labels: DataFrame) -> DataFrame:
    """w: weight of a match, non-matches over matches; 1 without matches."""
    n1, n0 = F.count_if(F.expr("label = 1")), F.count_if(F.expr("label = 0"))
    return labels.agg(F.coalesce(F.try_divide(n0.cast("double"), n1.cast("double")), F.lit(1.0)).alias("w"), n0.alias("n0"), n1.alias("n1"))


def feature_stats(incidence: DataFrame, labels: DataFrame) -> DataFrame:
    """feature_id, n0 s0 q0 n1 s1 q1 over the labeled pairs."""
    rows = incidence.select("pair_id", "feature_id", "x").join(labels.select("pair_id", "label"), "pair_id")
    on = lambda y, v: F.coalesce(F.sum(F.when(F.col("label") == y, v)), F.lit(0.0))
    x = F.col("x")
    return rows.groupBy("feature_id").agg(
        F.count_if(F.expr("label = 0")).alias("n0"), on(0, x).alias("s0"), on(0, x * x).alias("q0"),
        F.count_if(F.expr("label = 1")).alias("n1"), on(1, x).alias("s1"), on(1, x * x).alias("q1"),
    )


def add_stats(stats: DataFrame, more: DataFrame) -> DataFrame:
    """The sums of both: statistics are additive, so new evidence never needs the old evidence's entries."""
    return stats.unionByName(more).groupBy("feature_id").agg(*[F.sum(c).alias(c) for c in ("n0", "s0", "q0", "n1", "s1", "q1")])


def fit_curves(stats: DataFrame, weight: DataFrame, settings: Settings) -> DataFrame:
    """feature_id, tau, alpha, sigma, xbar, dev, nobs, active, lo, hi; weight is the one row of class_weight."""
    rows = stats.join(F.broadcast(weight.select("w")))
    w = F.col("w") if settings.class_weight else F.lit(1.0)
    return rows.select("feature_id", *[c.alias(name) for name, c in I.curve_columns(settings, w).items()])


def with_confidence(incidence: DataFrame, curves: DataFrame, settings: Settings) -> DataFrame:
    """pair_id, feature_id, x, theta (normalised), tau, alpha of entries with an active feature."""
    active = curves.where("active").withColumn("whole", I.whole_area(F.col("nobs") - 2))
    rows = incidence.select("pair_id", "feature_id", "x").join(active, "feature_id")
    theta = I.confidence(settings, F.col("x"), F.col("whole"))
    return rows.select("pair_id", "feature_id", "x", (I.normalize(theta) if settings.confidence_scale == "normalized" else theta).alias("theta"), "tau", "alpha")


def support(entries: DataFrame, settings: Settings | None = None) -> DataFrame:
    """pair_id, log_odds, support, features: evidence combined over a pair's features."""
    one = I.log_odds_of_support(F.col("theta"))
    total = F.avg(one) if settings and settings.support_mode == "mean_logit" else F.sum(one)
    out = entries.groupBy("pair_id").agg(total.alias("log_odds"), F.count(F.lit(1)).alias("features"))
    return out.withColumn("support", I.logistic(F.col("log_odds")))


def top_support(supports: DataFrame, m: int | None) -> DataFrame:
    return supports if m is None else supports.orderBy(F.desc(F.round("log_odds", 9)), "pair_id").limit(m)


def approx_probability(entries: DataFrame) -> DataFrame:
    """pair_id, z (summed factor weights), p, h."""
    z = F.sum(I.factor_weight(F.col("theta"), F.col("tau"), F.col("x"), F.col("alpha")))
    out = entries.groupBy("pair_id").agg(z.alias("z")).withColumn("p", I.logistic(F.col("z")))
    return out.withColumn("h", I.entropy(F.col("p")))


def top_certain(candidates: DataFrame, k: int) -> DataFrame:
    return candidates.orderBy(F.round("h", 9), "pair_id").limit(k)


def own_features(incidence: DataFrame, targets: DataFrame) -> DataFrame:
    """target, feature_id, x of the target pairs."""
    return incidence.join(F.broadcast(targets.select("pair_id")), "pair_id").select(F.col("pair_id").alias("target"), "feature_id", F.col("x").alias("target_x"))


def evidence_of(incidence: DataFrame, labels: DataFrame, targets: DataFrame) -> DataFrame:
    """feature_id, pair_id, x, label, bin of the labeled pairs that share a feature with a target."""
    asked = own_features(incidence, targets).select("feature_id").distinct()
    rows = incidence.select("pair_id", "feature_id", "x").join(F.broadcast(asked), "feature_id").join(labels.select("pair_id", "label"), "pair_id")
    return rows.withColumn("bin", I.interval(F.col("x")))


def capped(evidence: DataFrame, cap: int, salts: int = 1) -> DataFrame:
    """At most cap rows per feature and interval, in the order of a hash of the pair; hot cells are first cut within salts."""
    order = [hash_order("pair_id"), F.col("pair_id")]
    if salts > 1:
        evidence = evidence.withColumn("_s", F.pmod(F.xxhash64("pair_id"), F.lit(salts)))
        first = Window.partitionBy("feature_id", "bin", "_s").orderBy(*order)
        evidence = evidence.withColumn("_r", F.row_number().over(first)).where(F.col("_r") <= cap).drop("_s", "_r")
    w = Window.partitionBy("feature_id", "bin").orderBy(*order)
    return evidence.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= cap).drop("_r")


def subgraph(incidence: DataFrame, labels: DataFrame, targets: DataFrame, cap: int, salts: int = 8) -> DataFrame:
    """target, pair_id, feature_id, x, label, target_x: what one fit sees."""
    kept = capped(evidence_of(incidence, labels, targets), cap, salts)
    return own_features(incidence, targets).join(kept, "feature_id").select("target", "pair_id", "feature_id", "x", "label", "target_x")


def hops(incidence: DataFrame, targets: DataFrame, r: int, max_rows: int = 5_000_000) -> DataFrame:
    """target, pair_id within r steps over shared features; refuses to grow beyond max_rows."""
    near = targets.select(F.col("pair_id").alias("target"), "pair_id")
    edges = incidence.select("pair_id", "feature_id")
    for _ in range(r):
        by_feature = near.join(edges, "pair_id").select("target", "feature_id").distinct()
        near = by_feature.join(edges, "feature_id").select("target", "pair_id").distinct()
        if near.count() > max_rows:
            raise ValueError(f"over {max_rows} rows in the neighbourhood; use the capped subgraph")
    return near
