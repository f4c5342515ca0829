"""Relational operators that users of the methods need and Spark lacks or leaves to the caller."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.planner import connected_components


def range_join(left: DataFrame, right: DataFrame, point: str, lo: str, hi: str, bucket: float) -> DataFrame:
    """Rows of left whose point lies in [lo, hi] of right: an equi-join on the buckets that the interval covers, then the exact test."""
    a = left.withColumn("_b", F.floor(F.col(point) / bucket))
    b = right.withColumn("_b", F.explode(F.sequence(F.floor(F.col(lo) / bucket), F.floor(F.col(hi) / bucket))))
    return a.join(b, "_b").where((F.col(point) >= F.col(lo)) & (F.col(point) <= F.col(hi))).drop("_b")


def asof_join(left: DataFrame, right: DataFrame, keys: list[str], at: str, value_cols: list[str]) -> DataFrame:
    """Each left row with the last right row of its keys at or before its time: one sort over the union, no inequality join."""
    carried = F.struct(F.col(at).alias("_at"), *[F.col(c) for c in value_cols])
    a = left.withColumn("_v", F.lit(None).cast(right.select(carried.alias("v")).schema["v"].dataType)).withColumn("_side", F.lit(1))
    b = right.select(*keys, at, carried.alias("_v"), F.lit(0).alias("_side"))
    both = a.unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy(*keys).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = both.withColumn("_v", F.last("_v", ignorenulls=True).over(w)).where("_side = 1")
    return out.select(*left.columns, F.col("_v._at").alias(f"{at}_right"), *[F.col(f"_v.{c}").alias(f"{c}_right") for c in value_cols])


def interval_join(left: DataFrame, right: DataFrame, keys: list[str], at: str, seconds: int) -> DataFrame:
    """Pairs of rows of equal keys at most so many seconds apart, right at or before left; buckets of that length make it an equi-join."""
    sec = lambda c: F.unix_micros(c.cast("timestamp")) / 1e6
    a = left.withColumn("_b", F.floor(sec(F.col(at)) / seconds))
    r = right.select(*keys, *[F.col(c).alias(f"{c}_right") for c in right.columns if c not in keys])
    b = r.withColumn("_c", F.floor(sec(F.col(f"{at}_right")) / seconds)).withColumn("_b", F.explode(F.array(F.col("_c"), F.col("_c") + 1))).drop("_c")
    gap = F.unix_micros(F.col(at).cast("timestamp")) - F.unix_micros(F.col(f"{at}_right").cast("timestamp"))
    return a.join(b, [*keys, "_b"]).where((gap >= 0) & (gap <= seconds * 1_000_000)).drop("_b")


def salted_join(left: DataFrame, right: DataFrame, keys: list[str], salts: int = 16, hot_rows: int = 100_000) -> DataFrame:
    """An inner join whose hot keys are spread: left rows of keys with over hot_rows rows get a salt, and of the right table the rows of these keys alone are repeated for each.

    Null keys meet nothing and are no hot keys. At most so many keys are hot as the left table has rows a hot_rows, so they are broadcast; the tables are shuffled, never broadcast.
    """
    found = left.where(" and ".join(f"`{k}` is not null" for k in keys)).groupBy(*keys).agg(F.count(F.lit(1)).alias("_n"))
    hot = F.broadcast(found.where(F.col("_n") > hot_rows).select(*keys, F.lit(True).alias("_hot")))
    salt = F.pmod(F.monotonically_increasing_id(), F.lit(salts)).cast("int")
    a = left.withColumn("_s", salt).join(hot, keys, "left").withColumn("_s", F.when(F.col("_hot"), F.col("_s")).otherwise(0)).drop("_hot")
    b = right.join(hot, keys, "left").withColumn("_s", F.explode(F.sequence(F.lit(0), F.when(F.col("_hot"), salts - 1).otherwise(0)))).drop("_hot")
    return a.join(b.hint("merge"), [*keys, "_s"]).drop("_s")


def top_per_group(df: DataFrame, keys: list[str], order: list[Column], n: int) -> DataFrame:
    w = Window.partitionBy(*keys).orderBy(*order)
    return df.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= n).drop("_r")


def hash_part(key: Column, parts: int, seed: int = 0) -> Column:
    """Deterministic part of a row, by MD5, which other engines have too."""
    return F.pmod(F.conv(F.substring(F.md5(F.concat_ws("|", key.cast("string"), F.lit(str(seed)))), 1, 8), 16, 10).cast("bigint"), F.lit(parts)).cast("int")


def cluster_matches(labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """rec_id, cluster (least id) of every record in a match."""
    links = pairs.join(labels.where("label = 1").select("pair_id"), "pair_id", "left_semi").select("id_a", "id_b")
    return connected_components(links, "id_a", "id_b").select(F.col("node").alias("rec_id"), F.col("root").alias("cluster"))


def canonical(records: DataFrame, clusters: DataFrame, cols: list[str]) -> DataFrame:
    """Of each cluster the most frequent value of each column, ties to the least."""
    rows = records.join(clusters, "rec_id")
    out = rows.select("cluster").distinct()
    for c in cols:
        counts = rows.where(F.col(c).isNotNull()).groupBy("cluster", c).agg(F.count(F.lit(1)).alias("_n"))
        best = top_per_group(counts, ["cluster"], [F.desc("_n"), F.asc(c)], 1).select("cluster", c)
        out = out.join(best, "cluster", "left")
    return out


def one_to_one(pairs: DataFrame, score: str) -> DataFrame:
    """Pairs that are the best of both their records; ties by pair_id."""
    a = F.row_number().over(Window.partitionBy("id_a").orderBy(F.desc(score), "pair_id"))
    b = F.row_number().over(Window.partitionBy("id_b").orderBy(F.desc(score), "pair_id"))
    return pairs.withColumn("_a", a).withColumn("_b", b).where("_a = 1 and _b = 1").drop("_a", "_b")
