"""Exact deduplication with skew-safe combining; DataFrame functions only.

Stages: equal texts meet inside each task (partial aggregation), then inside
salted digest groups, then the salts' winners meet globally. At every stage rows
combine only if their whole normalised texts are equal; the digest alone never
decides. A hot text costs each task one row, whatever the number of its copies.

Defined results: null and empty texts are equal to each other; rows that repeat
a doc_id within a group all count as kept if the id is the largest, but
``drop_copies`` leaves one row of each group; a group whose ids are all null keeps
them (``drop_copies``: one of them); an empty table gives an empty result; columns
other than the two named ones play no part. Two different texts with one
SHA-256 digest would stop the job with an error rather than be merged.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import ascii_lower, materialize

#: A text with over one in so many of all rows is hot, so at most so many texts are.
HOT_PARTS = 1000


def digested(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, norm, digest (binary SHA-256 of the normalised text)."""
    rows = docs.select(F.col(id_col).alias("doc_id"), ascii_lower(F.col(text_col)).alias("norm"))
    return rows.withColumn("digest", F.unhex(F.sha2("norm", 256)))


def dedup_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", salts: int = 8) -> DataFrame:
    """One row per distinct text: digest, keep_id (largest id), group_size."""
    salted = digested(docs, id_col, text_col).withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(salts)))
    winners = salted.groupBy("digest", "salt", "norm").agg(F.max("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("n"))
    texts = winners.groupBy("digest", "norm").agg(F.max("keep_id").alias("keep_id"), F.sum("n").alias("n"))
    one_text = F.when(F.count(F.lit(1)) == 1, F.max("keep_id")).otherwise(
        F.raise_error(F.lit("two texts share a SHA-256 digest")).cast("bigint")
    )
    return texts.groupBy("digest").agg(one_text.alias("keep_id"), F.sum("n").alias("group_size"))


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", salts: int = 8) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256.

    The few hot groups (at most HOT_PARTS, by their definition) are broadcast, and
    their documents get a key of their own, so no task of the join gets them all.
    """
    groups = materialize(dedup_groups(docs, id_col, text_col, salts), "exact-groups")
    total = groups.agg(F.coalesce(F.sum("group_size"), F.lit(0))).first()[0]
    hot = groups.where(F.col("group_size") * HOT_PARTS > total).select(
        F.col("digest").alias("hot_digest"), F.col("keep_id").alias("hot_keep"), F.col("group_size").alias("hot_size")
    )
    rows = digested(docs, id_col, text_col).drop("norm")
    rows = rows.join(F.broadcast(hot), F.col("digest") == F.col("hot_digest"), "left")
    spread = F.unhex(F.sha2(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), 256))
    rows = rows.withColumn("join_key", F.when(F.col("hot_size").isNull(), F.col("digest")).otherwise(spread))
    out = rows.join(groups.withColumnRenamed("digest", "join_key"), "join_key", "left")
    keep = F.when(F.col("hot_size").isNull(), F.col("keep_id")).otherwise(F.col("hot_keep"))
    return out.select(
        "doc_id",
        keep.alias("keep_id"),
        F.coalesce("hot_size", "group_size").alias("group_size"),
        F.col("doc_id").eqNullSafe(keep).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", salts: int = 8) -> DataFrame:
    """One row of each group of equal texts, with all its columns: one with the largest id; of rows that repeat that id too, the first by text, then by a hash of the other columns.

    Rows and winners meet by digest and id together, so the copies of a hot text, which differ in their ids, go to many tasks.
    """
    names = docs.columns
    groups = dedup_groups(docs, id_col, text_col, salts)
    id_key = F.coalesce(F.col(id_col).cast("string"), F.lit("null"))
    rows = docs.withColumn("_digest", F.unhex(F.sha2(ascii_lower(F.col(text_col)), 256))).withColumn("_id", id_key)
    winners = groups.select(F.col("digest").alias("_digest"), F.coalesce(F.col("keep_id").cast("string"), F.lit("null")).alias("_id"))
    plain = [F.col(f"`{c}`").cast("string") for c in names]
    one = Window.partitionBy("_digest", "_id").orderBy(F.coalesce(F.col(text_col), F.lit("")), F.xxhash64(*plain))
    kept = rows.join(winners, ["_digest", "_id"], "left_semi").withColumn("_copy", F.row_number().over(one)).where(F.col("_copy") == 1)
    return kept.select(*[F.col(f"`{c}`") for c in names])
