"""Helpers that several operators of this subpackage share."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z and nothing else; null counts as empty.

    ``lower`` is much faster than ``translate`` and gives the same wherever no
    other character has a case to lose.
    """
    t = F.coalesce(text, F.lit(""))
    plain = (F.octet_length(t) == F.length(t)) | ~t.rlike(r"[\x{80}-\x{10FFFF}&&[\p{IsUppercase}\p{Lt}]]")
    return F.when(plain, F.lower(t)).otherwise(F.translate(t, UPPER, UPPER.lower()))


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``; its own only where none is set, as in tests."""
    sc = spark.sparkContext
    found = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not found:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = tempfile.mkdtemp(prefix="pairlabel-")
        sc.setCheckpointDir(found)
    return found.rstrip("/")


_written: list[tuple[SparkSession, str]] = []


def shared_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    return path


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Writes a table into the shared folder and rereads it: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = shared_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release() -> None:
    """Deletes what :func:`materialize` has written; results that read it must be used before."""
    while _written:
        spark, path = _written.pop()
        try:
            p = spark._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
        except Exception:  # noqa: BLE001  the session has ended; a cluster's own cleaning takes over
            return


atexit.register(release)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


#: A key with over one in so many of all rows is hot, so at most so many keys are.
HOT_PARTS = 1000


def hot_join(rows: DataFrame, groups: DataFrame, key: str, size: str, total: int, spread: Column) -> DataFrame:
    """rows left-joined with groups (one row per key, with its number of rows) on key; hot keys are broadcast, and their rows get the key ``spread`` instead, so no task gets them all.

    spread has the key's type and matches no key, or the key of a row that it does not harm to meet. The columns of groups follow, but for size.
    """
    values = [c for c in groups.columns if c != key]
    hot = groups.where(F.col(size) * HOT_PARTS > total).select(F.col(key).alias("_hot_key"), *[F.col(c).alias(f"_hot_{c}") for c in values])
    out = rows.join(F.broadcast(hot), F.col(key) == F.col("_hot_key"), "left")
    out = out.withColumn("_key", F.when(F.col("_hot_key").isNull(), F.col(key)).otherwise(spread))
    out = out.join(groups.select(F.col(key).alias("_key"), *values), "_key", "left")
    for c in values:
        out = out.withColumn(c, F.when(F.col("_hot_key").isNull(), F.col(c)).otherwise(F.col(f"_hot_{c}")))
    return out.drop("_key", "_hot_key", *[f"_hot_{c}" for c in values])
