"""Plan choice at the DataFrame level: set-similarity joins and connected components."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Below this product of row counts the nested loop is the cheapest plan.
NESTED_LOOP_PAIRS = 250_000


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; its own only where none is set, in local mode."""
    sc = spark.sparkContext
    found = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not found:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = tempfile.mkdtemp(prefix="pairlabel-")
        sc.setCheckpointDir(found)
    return found.rstrip("/")


def cut(df: DataFrame, name: str) -> DataFrame:
    """Writes and rereads a table in the shared folder, so lineage ends there."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def prefix_join(left: DataFrame, right: DataFrame, threshold: float) -> DataFrame:
    """id_a, id_b, sim: pairs of (rec_id, s) with Jaccard of the sets at or over the threshold.

    Tokens are ordered by document frequency, rarest first; of two similar sets the
    first size - ceil(threshold * size) + 1 tokens meet. Sizes that differ too much never
    meet. What two prefixes share is counted: behind the last shared token at most the
    shorter remainder can be shared too, and pairs for which that is not enough are not
    read. What is left is compared exactly.
    """
    tokens = left.select(F.explode("s").alias("t")).unionAll(right.select(F.explode("s").alias("t")))
    df = tokens.groupBy("t").agg(F.count(F.lit(1)).alias("df"))

    def prefixes(table: DataFrame, name: str) -> DataFrame:
        rows = table.select("rec_id", F.size("s").alias("n"), F.explode("s").alias("t")).join(df, "t")
        rows = rows.groupBy("rec_id", "n").agg(F.array_sort(F.collect_list(F.struct("df", "t"))).alias("o"))
        length = F.col("n") - F.ceil(F.col("n") * threshold) + 1
        return rows.select(F.col("rec_id").alias(f"id_{name}"), F.col("n").alias(f"n_{name}"), F.posexplode(F.slice("o", F.lit(1), length.cast("int"))).alias("at", "x")).select(
            f"id_{name}", f"n_{name}", (F.col(f"n_{name}") - F.col("at") - 1).alias(f"rest_{name}"), F.col("x.t").alias("t")
        )

    near = (F.col("n_a") >= F.col("n_b") * threshold) & (F.col("n_b") >= F.col("n_a") * threshold)
    rest = F.least("rest_a", "rest_b")
    met = prefixes(left, "a").join(prefixes(right, "b"), "t").where(near).groupBy("id_a", "id_b", "n_a", "n_b").agg(F.count(F.lit(1)).alias("c"), F.min(rest).alias("rest"))
    met = met.where((F.col("c") + F.col("rest")) * (1 + threshold) >= (F.col("n_a") + F.col("n_b")) * threshold - 1e-9).select("id_a", "id_b")
    met = met.join(left.select(F.col("rec_id").alias("id_a"), F.col("s").alias("s_a")), "id_a").join(right.select(F.col("rec_id").alias("id_b"), F.col("s").alias("s_b")), "id_b")
    return _kept(met, threshold)


def short_join(left: DataFrame, right: DataFrame, threshold: float, df_max: int = 0, min_shared: int = 1) -> DataFrame:
    """id_a, id_b, sim: the same pairs for short sets (rec_id, s, and n_records, how many records have the set), without a shuffle of candidates.

    Each row of a prefix carries its whole set as numbers in the order of frequency, so a
    pair is compared where it meets, and is given by its first shared token alone. A pair
    of sizes that share too little behind this token is not compared. Left out are pairs
    that share min_shared tokens of at most df_max records (of both tables, or of the one
    if both are the same).
    """
    one = left is right
    tokens = left.select("n_records", F.explode("s").alias("t"))
    if not one:
        tokens = tokens.unionAll(right.select("n_records", F.explode("s").alias("t")))
    df = tokens.groupBy("t").agg(F.count(F.lit(1)).alias("df"), (F.sum("n_records") <= df_max).cast("long").alias("rare"))
    ordered = df.repartitionByRange("df", "t").sortWithinPartitions("df", "t")
    code = cut(ordered.select("t", (F.monotonically_increasing_id() * 2 + F.col("rare")).alias("code")), "codes")  # odd: rare

    def prefixes(table: DataFrame, name: str) -> DataFrame:
        rows = table.select("rec_id", F.explode("s").alias("t")).join(code, "t")
        rows = rows.groupBy("rec_id").agg(F.array_sort(F.collect_list("code")).alias("o")).withColumn("n", F.size("o"))
        length = (F.col("n") - F.ceil(F.col("n") * threshold - 1e-9) + 1).cast("int")
        head = F.posexplode(F.slice("o", F.lit(1), length)).alias("at", "t")
        return rows.select("rec_id", "n", "o", head).select(F.col("rec_id").alias(f"id_{name}"), F.col("n").alias(f"n_{name}"), F.col("o").alias(f"o_{name}"), (F.col("n") - F.col("at")).alias(f"rest_{name}"), "t")

    need = (F.col("n_a") + F.col("n_b")) * threshold - 1e-9
    met = prefixes(left, "a").join(prefixes(right, "b").hint("merge"), "t").where(F.least("rest_a", "rest_b") * (1 + threshold) >= need)
    met = met.select("id_a", "id_b", "n_a", "n_b", "t", F.array_intersect("o_a", "o_b").alias("both"))
    c = F.size("both")
    met = met.where((c * (1 + threshold) >= need) & (F.col("both")[0] == F.col("t")) & (F.size(F.filter("both", lambda x: x % 2 == 1)) < min_shared))
    return met.select("id_a", "id_b", (c / (F.col("n_a") + F.col("n_b") - c)).alias("sim")).where(F.col("sim") >= threshold)


def loop_join(left: DataFrame, right: DataFrame, threshold: float) -> DataFrame:
    """The same by comparing every pair, for small tables."""
    a = left.select(F.col("rec_id").alias("id_a"), F.col("s").alias("s_a"))
    return _kept(a.crossJoin(right.select(F.col("rec_id").alias("id_b"), F.col("s").alias("s_b"))), threshold)


def _kept(met: DataFrame, threshold: float) -> DataFrame:
    both = F.size(F.array_intersect("s_a", "s_b"))
    sim = both / F.when(F.size(F.array_union("s_a", "s_b")) > 0, F.size(F.array_union("s_a", "s_b")))
    return met.select("id_a", "id_b", sim.alias("sim")).where(F.col("sim") >= threshold)


def explain_choice(left: DataFrame, right: DataFrame) -> str:
    return "loop" if left.count() * right.count() <= NESTED_LOOP_PAIRS else "prefix"


def similarity_join(left: DataFrame, right: DataFrame, threshold: float, how: str | None = None) -> DataFrame:
    """Chooses by counted cost between the nested loop and the prefix filter."""
    how = how or explain_choice(left, right)
    return (loop_join if how == "loop" else prefix_join)(left, right, threshold)


def token_classes(table: DataFrame) -> DataFrame:
    """rec_id, class_id, s (sorted): the least id of the records with the same set of tokens. Empty sets are in no class. One row per class meets its members, so adaptive execution can split a hot class."""
    rows = table.select("rec_id", F.array_sort(F.array_distinct("s")).alias("s")).where(F.size("s") > 0)
    least = rows.groupBy("s").agg(F.min("rec_id").alias("class_id"))
    return rows.join(least, "s").select("rec_id", "class_id", "s")


def class_heads(table: DataFrame) -> DataFrame:
    """rec_id, s: the least record of each class of equal sets; combined before the shuffle, so copies cost one row each partition."""
    rows = table.select("rec_id", F.array_sort(F.array_distinct("s")).alias("s")).where(F.size("s") > 0)
    return rows.groupBy("s").agg(F.min("rec_id").alias("rec_id"), F.count(F.lit(1)).alias("n_records")).select("rec_id", "s", "n_records")


def similar_classes(table: DataFrame, threshold: float) -> DataFrame:
    """id_a, id_b, sim, copy: a set-similarity join of a table with itself that never expands copies.

    copy is false for pairs of classes of equal sets, each named by its least record, and
    true for a record and the least record of its own class. Any two records whose sets are
    similar are in one class or in two that are paired.
    """
    heads = class_heads(table)
    links = prefix_join(heads, heads, threshold).where("id_a < id_b").withColumn("copy", F.lit(False))
    copies = token_classes(table).where("rec_id <> class_id").select(F.col("class_id").alias("id_a"), F.col("rec_id").alias("id_b"), F.lit(1.0).alias("sim"), F.lit(True).alias("copy"))
    return links.unionByName(copies)


def connected_components(links: DataFrame, a: str, b: str) -> DataFrame:
    """node, root (the least node that can be reached). Rounds of least labels with jumps; each round's labels are written, so lineage stays short."""
    both = cut(links.select(F.col(a).alias("x"), F.col(b).alias("y")).unionAll(links.select(F.col(b), F.col(a))).distinct(), "links")
    labels = cut(both.groupBy(F.col("x").alias("node")).agg(F.least(F.min("y"), F.col("x")).alias("root")), "labels")
    while True:
        around = both.join(labels, F.col("y") == F.col("node")).groupBy("x").agg(F.min("root").alias("near"))
        lower = labels.join(around, F.col("node") == F.col("x"), "left").select("node", "root", F.least("root", "near").alias("next"))
        jump = labels.select(F.col("node").alias("_n"), F.col("root").alias("_r"))
        new = lower.join(jump, F.col("next") == F.col("_n"), "left").select("node", F.least("next", F.coalesce("_r", "next")).alias("root"), F.col("root").alias("was"))
        new = cut(new, "labels")
        labels = new.select("node", "root")
        if not new.where("root <> was").limit(1).count():
            return labels
