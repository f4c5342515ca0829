"""Measures of accuracy and cost. labels: pair_id, label; truth: pair_id, truth."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def _counts(labels: DataFrame, truth: DataFrame) -> DataFrame:
    rows = labels.select("pair_id", "label").join(truth.select("pair_id", "truth"), "pair_id")
    return rows.agg(
        F.count_if((F.col("label") == 1) & (F.col("truth") == 1)).alias("tp"),
        F.count_if((F.col("label") == 1) & (F.col("truth") == 0)).alias("fp"),
        F.count_if((F.col("label") == 0) & (F.col("truth") == 1)).alias("fn"),
        F.count_if((F.col("label") == 0) & (F.col("truth") == 0)).alias("tn"),
    )


def _share(a: Column, b: Column) -> Column:
    return F.coalesce(F.try_divide(a.cast("double"), b.cast("double")), F.lit(0.0))


def confusion(labels: DataFrame, truth: DataFrame) -> DataFrame:
    return _counts(labels, truth)


def quality(labels: DataFrame, truth: DataFrame, missed: int = 0) -> DataFrame:
    """precision, recall, f1 and recall_all, which also counts matches lost in blocking."""
    return quality_of(_counts(labels, truth), missed)


def quality_of(c: DataFrame, missed: int = 0) -> DataFrame:
    """The same from the counts tp, fp, fn."""
    p, r = _share(F.col("tp"), F.col("tp") + F.col("fp")), _share(F.col("tp"), F.col("tp") + F.col("fn"))
    out = c.select(p.alias("precision"), r.alias("recall"), _share(F.col("tp"), F.col("tp") + F.col("fn") + missed).alias("recall_all"))
    return out.withColumn("f1", _share(2 * F.col("precision") * F.col("recall"), F.col("precision") + F.col("recall")))


def precision(labels: DataFrame, truth: DataFrame) -> DataFrame:
    return quality(labels, truth).select("precision")


def recall(labels: DataFrame, truth: DataFrame, missed: int = 0) -> DataFrame:
    return quality(labels, truth, missed).select("recall", "recall_all")


def f1(labels: DataFrame, truth: DataFrame) -> DataFrame:
    return quality(labels, truth).select("f1")


def precision_by_interval(pairs: DataFrame, truth: DataFrame, bins: int = 10) -> DataFrame:
    """bin, n, matches, precision of each similarity interval."""
    rows = pairs.select("pair_id", F.least(F.floor(F.col("sim") * bins), F.lit(bins - 1)).cast("int").alias("bin")).join(truth, "pair_id")
    out = rows.groupBy("bin").agg(F.count(F.lit(1)).alias("n"), F.sum("truth").cast("bigint").alias("matches"))
    return out.withColumn("precision", F.col("matches") / F.col("n"))


def monotonicity_violations(intervals: DataFrame) -> DataFrame:
    """Neighbouring intervals whose precision falls: how many, and how many pairs lie in the later ones. The table has a row per interval."""
    w = Window.orderBy("bin")
    rows = intervals.withColumn("before", F.lag("precision").over(w))
    falls = F.coalesce(F.col("precision") < F.col("before"), F.lit(False))
    return rows.agg(F.count_if(falls).alias("violations"), F.coalesce(F.sum(F.when(falls, F.col("n"))), F.lit(0)).cast("bigint").alias("pairs"))


def bound_purity(pairs: DataFrame, truth: DataFrame, lo: float, hi: float) -> DataFrame:
    """Share of matches at or over hi, and of non-matches at or under lo."""
    rows = pairs.select("pair_id", "sim").join(truth, "pair_id")
    over, under = F.col("sim") >= hi, F.col("sim") <= lo
    return rows.agg(
        _share(F.count_if(over & (F.col("truth") == 1)), F.count_if(over)).alias("match_purity"),
        _share(F.count_if(under & (F.col("truth") == 0)), F.count_if(under)).alias("nonmatch_purity"),
    )


def flip_rate(round_log: DataFrame) -> DataFrame:
    """Labels that the fit decided otherwise than the approximation, by tenth of the rounds."""
    top = round_log.agg(F.max("round").alias("top"))
    rows = round_log.join(F.broadcast(top))
    tenth = F.least(F.floor(F.col("round") * 10 / (F.col("top") + 1)), F.lit(9)).cast("int")
    return rows.groupBy(tenth.alias("tenth")).agg(F.count(F.lit(1)).alias("labels"), F.count_if("flipped").alias("flips"))


def cost_multiple(timings: DataFrame) -> DataFrame:
    """size, seconds, multiple of the smallest size's seconds. A row per size."""
    return timings.withColumn("multiple", F.col("seconds") / F.first("seconds").over(Window.orderBy("size")))


def feature_density(incidence: DataFrame) -> DataFrame:
    per = incidence.groupBy("pair_id").agg(F.count(F.lit(1)).alias("n"))
    total = incidence.agg(F.count_distinct("feature_id").alias("features"))
    return per.agg(F.count(F.lit(1)).alias("pairs"), F.avg("n").alias("features_per_pair"), F.max("n").alias("most")).join(F.broadcast(total))


def average_runs(runs: DataFrame) -> DataFrame:
    """Means over runs, and the F1 of the mean precision and recall, which is another number."""
    p, r = F.avg("precision"), F.avg("recall")
    return runs.groupBy("method").agg(p.alias("precision"), r.alias("recall"), F.avg("f1").alias("f1"), F.stddev("f1").alias("f1_sd"), _share(2 * p * r, p + r).alias("f1_of_means"))


def blocking_quality(pairs: DataFrame, truth: DataFrame, matches: int, possible: int) -> DataFrame:
    """Share of all matches that the pairs hold, and share of all possible pairs that they avoid."""
    hit = pairs.select("pair_id").join(truth.where("truth = 1"), "pair_id", "left_semi").agg(F.count(F.lit(1)).alias("hit"))
    n = pairs.agg(F.count(F.lit(1)).alias("n"))
    return hit.join(F.broadcast(n)).select((F.col("hit") / F.lit(matches)).alias("completeness"), (1 - F.col("n") / F.lit(possible)).alias("reduction"))
