"""Features of pairs: attribute similarities, common token runs, shared and unshared rare tokens.

The incidence table (pair_id, feature_id, x) is the factor graph's edge list. Feature
ids are hashes of (family, attribute, token), so no pass over the features is needed.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import similarity as S
from .workload import PARTS


def feature_id(family: Column, attr: Column, token: Column) -> Column:
    """A positive number of 60 bits from MD5, which other engines have too."""
    text = F.concat_ws("|", family, attr, token)
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint")


def attr_features(pairs: DataFrame, attrs: tuple[str, ...] = PARTS) -> DataFrame:
    """pair_id, family, attr, token, x."""
    rows = pairs.select("pair_id", *attrs).unpivot("pair_id", list(attrs), "attr", "x")
    return rows.select("pair_id", F.lit("attr").alias("family"), "attr", F.lit("").alias("token"), "x")


def title_metrics() -> dict[str, Column]:
    """Metrics that a short attribute can have besides the set similarity: Jaro-Winkler, edit, and the mean of set and edit similarity."""
    a, b = F.col("title_a"), F.col("title_b")
    whole_a, whole_b = F.array_join(a, " "), F.array_join(b, " ")
    return {"jw_title": S.jaro_winkler(whole_a, whole_b), "edit_title": S.edit_sim(whole_a, whole_b), "hybrid_title": S.hybrid(a, b)}


def lcs_features(pairs: DataFrame, attrs: tuple[str, ...] = ("title",)) -> DataFrame:
    """Of an attribute other than the title, which may be very long, in Arrow batches."""
    out = None
    for a in attrs:
        x = (S.lcs_share if a == "title" else S.lcs_share_long)(F.col(f"{a}_a"), F.col(f"{a}_b"))
        one = pairs.select("pair_id", F.lit("lcs").alias("family"), F.lit(a).alias("attr"), F.lit("").alias("token"), x.alias("x"))
        out = one if out is None else out.unionAll(one)
    return out


def _tokens(pairs: DataFrame, family: str, attr: str, tokens: Column) -> DataFrame:
    """A token's curve runs over the pair's similarity."""
    return pairs.select("pair_id", F.lit(family).alias("family"), F.lit(attr).alias("attr"), F.explode(tokens).alias("token"), F.col("sim").alias("x"))


def same_token_features(pairs: DataFrame, attr: str = "title") -> DataFrame:
    return _tokens(pairs, "same", attr, F.array_intersect(f"{attr}_a", f"{attr}_b"))


def diff_token_features(pairs: DataFrame, attr: str = "title") -> DataFrame:
    a, b = F.col(f"{attr}_a"), F.col(f"{attr}_b")
    return _tokens(pairs, "diff", attr, F.concat(F.array_except(a, b), F.array_except(b, a)))


def document_frequency(records: DataFrame, tokens_col: str = "title") -> DataFrame:
    """token, df, idf (natural logarithm over the records)."""
    n = records.select(F.count(F.lit(1)).alias("n"))
    df = records.select(F.explode(F.array_distinct(tokens_col)).alias("token")).groupBy("token").agg(F.count(F.lit(1)).alias("df"))
    return df.join(F.broadcast(n)).select("token", "df", F.ln(F.col("n") / F.col("df")).alias("idf"))


def discriminating_tokens(records: DataFrame, idf_min: float = 3.0, df_min: int = 2, tokens_col: str = "title") -> DataFrame:
    return document_frequency(records, tokens_col).where((F.col("idf") >= idf_min) & (F.col("df") >= df_min))


def informative(incidence: DataFrame, labels: DataFrame) -> DataFrame:
    """Features that touch both labeled and unlabeled pairs; others convey nothing."""
    rows = incidence.join(labels.select("pair_id", F.lit(1).alias("known")), "pair_id", "left")
    kept = rows.groupBy("feature_id").agg(F.count("known").alias("k"), F.count(F.lit(1)).alias("n")).where("k > 0 and k < n")
    return incidence.join(kept.select("feature_id"), "feature_id", "left_semi")


def incidence(pairs: DataFrame, records: DataFrame, idf_min: float = 3.0, df_min: int = 2, scope: str = "attr", token_attrs: tuple[str, ...] = ("title",), lcs_attrs: tuple[str, ...] = ("title",), same_attrs: tuple[str, ...] = (), metrics: tuple[str, ...] = ()) -> DataFrame:
    """pair_id, feature_id, family, attr, token, x.

    scope: a token counts per attribute or over the whole record; token_attrs: attributes with shared and unshared tokens;
    same_attrs: with shared ones alone, for long texts, which differ in hundreds; metrics: names of title_metrics.
    Bodies are needed (with_bodies) where an attribute is the body.
    """
    of_title = title_metrics()
    extra = pairs.withColumns({m: of_title[m] for m in metrics}) if metrics else pairs
    out = attr_features(extra, (*PARTS, *metrics)).unionByName(lcs_features(pairs, lcs_attrs))
    for a in (*token_attrs, *same_attrs):
        rare = discriminating_tokens(records, idf_min, df_min, a).select("token")
        both = same_token_features(pairs, a)
        if a in token_attrs:
            both = both.unionByName(diff_token_features(pairs, a))
        out = out.unionByName(both.join(rare, "token", "left_semi"))
    if scope == "record":
        out = out.withColumn("attr", F.when(F.col("family").isin("same", "diff"), F.lit("record")).otherwise(F.col("attr")))
        out = out.groupBy("pair_id", "family", "attr", "token").agg(F.max("x").alias("x"))
    return out.select("pair_id", feature_id(F.col("family"), F.col("attr"), F.col("token")).alias("feature_id"), "family", "attr", "token", "x")
