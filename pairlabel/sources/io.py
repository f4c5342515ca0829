"""Reading records and writing results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def register(spark: SparkSession, sf_dir: str, tables: tuple[str, ...] = TABLES) -> None:
    """Temporary views of the given tables."""
    for t in tables:
        load(spark, sf_dir, t).createOrReplaceTempView(t)


def read_records(spark: SparkSession, path: str, fmt: str, schema: T.StructType, bad: str = "permissive", **options) -> DataFrame:
    """CSV, JSON lines, text, ORC or Parquet with an explicit schema. bad: permissive keeps broken rows in a column, drop leaves them out, fail stops."""
    reader = spark.read.options(**options)
    if fmt in ("csv", "json"):
        reader = reader.option("mode", {"permissive": "PERMISSIVE", "drop": "DROPMALFORMED", "fail": "FAILFAST"}[bad])
        if bad == "permissive":
            schema = T.StructType([*schema.fields, T.StructField("_broken", T.StringType())])
            reader = reader.option("columnNameOfCorruptRecord", "_broken")
    if fmt == "text":
        return reader.text(path)
    return reader.schema(schema).format(fmt).load(path)


def read_jdbc(spark: SparkSession, url: str, table: str, key: str, low: int, high: int, parts: int, **options) -> DataFrame:
    """A table in parts by ranges of a key."""
    return spark.read.jdbc(url, table, column=key, lowerBound=low, upperBound=high, numPartitions=parts, properties=options)


def page_records(pages: DataFrame) -> DataFrame:
    """page_id, title, body (text without tags) of HTML pages."""
    html = F.coalesce("html", F.lit(""))
    title = F.trim(F.regexp_extract(html, r"(?is)<title[^>]*>(.*?)</title>", 1))
    body = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    body = F.regexp_replace(body, r"(?s)<[^>]*>", " ")
    for mark, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
        body = F.replace(body, F.lit(mark), F.lit(char))
    return pages.select("page_id", title.alias("title"), F.trim(F.regexp_replace(body, r"\s+", " ")).alias("body"))


def write_labels(log: DataFrame, path: str, mode: str = "append") -> None:
    """The round log, a folder per round."""
    log.write.mode(mode).partitionBy("round").parquet(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A table whose joins on the key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def unlabeled(pairs: DataFrame, log: DataFrame) -> DataFrame:
    """What a resumed run has still to do."""
    return pairs.join(log.select("pair_id"), "pair_id", "left_anti")
