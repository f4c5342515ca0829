"""Structured Streaming forms. Each takes a streaming DataFrame; run_once drains a file source into a table."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import BooleanType, StructField, StructType

from ..plans.planner import shared_dir


def read_stream(spark: SparkSession, sf_dir: str, table: str, files: int = 1) -> DataFrame:
    """A given table as a stream of files."""
    path = f"{sf_dir}/{table}.parquet"
    schema = spark.read.parquet(path).schema
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files)
    if place.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(place).isDirectory():
        rows = reader.parquet(path)
    else:  # a stream watches a folder, so a single file is picked out of its own
        rows = reader.option("pathGlobFilter", f"{table}.parquet").parquet(sf_dir)
    # event time needs an instant; stored times without a zone are read in the session's
    naive = [f.name for f in schema if f.dataType.simpleString() == "timestamp_ntz"]
    return rows.withColumns({c: F.col(c).cast("timestamp") for c in naive}) if naive else rows


def naive_times(df: DataFrame) -> DataFrame:
    """Instants as times without a zone again."""
    return df.select(*[F.col(c).cast("timestamp_ntz").alias(c) if t == "timestamp" else F.col(c) for c, t in df.dtypes])


def run_once(stream: DataFrame, mode: str = "append", key: list[str] | None = None) -> DataFrame:
    """Processes all there is, then returns the sink's rows. Complete and update modes keep the last rows of each key."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}-state").trigger(availableNow=True)
    if mode == "append":
        q = writer.format("parquet").option("path", base).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(base)
    q = writer.foreachBatch(idempotent_sink(base)).start()
    q.awaitTermination()
    rows = spark.read.parquet(f"{base}/*")
    if mode == "complete":
        return rows.join(F.broadcast(rows.agg(F.max("_batch").alias("_batch"))), "_batch").drop("_batch")
    last = rows.groupBy(*key).agg(F.max("_batch").alias("_batch"))
    return rows.join(last, [*key, "_batch"]).drop("_batch")


def idempotent_sink(path: str) -> Callable[[DataFrame, int], None]:
    """A batch overwrites its own folder, so a repeated batch leaves no second copy."""

    def write(batch: DataFrame, number: int) -> None:
        batch.withColumn("_batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write


def late_split(stream: DataFrame, delay: int, at: str = "ts") -> tuple[DataFrame, DataFrame]:
    """Rows on time, and late ones: more than so many seconds behind the latest time of all earlier batches, where a watermark would drop them.

    Each batch's latest time is kept beside its rows, so a repeated batch is judged as before. Rows without a time are on time.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    kind = stream.schema[at].dataType
    latest = lambda rows: rows.agg(F.max(at).cast(kind).alias("latest"))
    latest(spark.createDataFrame([], stream.schema)).write.parquet(f"{base}/latest/batch=-1")

    def write(batch: DataFrame, number: int) -> None:
        before = spark.read.parquet(f"{base}/latest").where(F.col("batch") < number).agg(F.max("latest").alias("_before"))
        late = F.col(at) < F.col("_before") - F.make_dt_interval(secs=F.lit(delay))
        rows = batch.join(F.broadcast(before)).withColumn("_late", F.coalesce(late, F.lit(False))).drop("_before")  # one row
        rows.write.mode("overwrite").parquet(f"{base}/rows/batch={number}")
        latest(spark.read.parquet(f"{base}/rows/batch={number}")).write.mode("overwrite").parquet(f"{base}/latest/batch={number}")

    stream.writeStream.option("checkpointLocation", f"{base}/state").trigger(availableNow=True).foreachBatch(write).start().awaitTermination()
    rows = spark.read.schema(StructType([*stream.schema.fields, StructField("_late", BooleanType())])).parquet(f"{base}/rows/*")
    return rows.where("not _late").drop("_late"), rows.where("_late").drop("_late")


def tumbling(events: DataFrame, size: str = "1 hour", late: str = "1 day") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", size), "event_type")
    return w.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, size: str = "6 hours", step: str = "3 hours", late: str = "1 day") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", size, step))
    return w.agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "n")


def session(events: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id")
    return w.agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def dedupe(events: DataFrame, keys: list[str], late: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def evidence_stats(entries: DataFrame) -> DataFrame:
    """Feature statistics of a stream of labeled entries (feature_id, x, label): the sums are additive."""
    on = lambda y, v: F.coalesce(F.sum(F.when(F.col("label") == y, v)), F.lit(0.0))
    x = F.col("x")
    return entries.groupBy("feature_id").agg(
        F.count_if(F.expr("label = 0")).alias("n0"), on(0, x).alias("s0"), on(0, x * x).alias("q0"),
        F.count_if(F.expr("label = 1")).alias("n1"), on(1, x).alias("s1"), on(1, x * x).alias("q1"),
    )


def score(entries: DataFrame, curves: DataFrame, settings) -> DataFrame:
    """Entries of new pairs against frozen curves, as factor weights; summed per pair by the reader."""
    from ..operators.graph import with_confidence

    return with_confidence(entries, curves, settings).select("pair_id", (F.col("theta") * F.col("tau") * (F.col("x") - F.col("alpha"))).alias("weight"))


def pairs_within(left: DataFrame, right: DataFrame, key: str, minutes: int) -> DataFrame:
    """Rows of two streams with one key, the right one at most so long before the left one."""
    a = left.withWatermark("ts", "1 day").alias("a")
    b = right.withWatermark("ts", "1 day").alias("b")
    near = F.expr(f"a.{key} = b.{key} AND b.ts <= a.ts AND b.ts >= a.ts - INTERVAL {minutes} MINUTES")
    return a.join(b, near).select(F.col("a.event_id").alias("event_id"), F.col("b.event_id").alias("event_id_right"))


def user_runs(events: DataFrame) -> DataFrame:
    """Stateful: per user the number of events seen and their summed value, one row per user and batch."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        for b in batches:
            n, total = n + len(b), total + float(b["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, total double", "n long, total double", "update", GroupStateTimeout.NoTimeout)
