"""Feature transforms for the baselines: scaled similarities, token vectors, vectors near to each other."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.ml import Pipeline
from pyspark.ml.feature import IDF, BucketedRandomProjectionLSH, CountVectorizer, HashingTF, Word2Vec
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .features import document_frequency
from .workload import PARTS


def scaled(pairs: DataFrame, cols: tuple[str, ...] = PARTS, how: str = "standard") -> DataFrame:
    """pair_id and the columns with mean 0 and deviation 1 (standard) or between 0 and 1 (range); a constant column becomes 0. The bounds are one row."""
    low, width = ("avg", "stddev_samp") if how == "standard" else ("min", "max")
    bounds = pairs.agg(*[F.expr(f"{f}({c})").alias(f"_{s}_{c}") for c in cols for s, f in (("low", low), ("width", width))])
    rows = pairs.select("pair_id", *cols).join(F.broadcast(bounds))

    def one(c: str):
        span = F.col(f"_width_{c}") if how == "standard" else F.col(f"_width_{c}") - F.col(f"_low_{c}")
        return F.coalesce((F.col(c) - F.col(f"_low_{c}")) / F.when(span > 1e-12, span), F.lit(0.0))

    return rows.select("pair_id", *[one(c).alias(c) for c in cols])


def tfidf(records: DataFrame, frequency: DataFrame, tokens_col: str = "title") -> DataFrame:
    """rec_id, token, weight: counts times inverse document frequency, the vector of a record of length 1; records of common words alone have none."""
    counted = records.select("rec_id", F.explode(tokens_col).alias("token")).groupBy("rec_id", "token").agg(F.count(F.lit(1)).alias("tf"))
    rows = counted.join(frequency.select("token", "idf"), "token").select("rec_id", "token", (F.col("tf") * F.col("idf")).alias("w"))
    length = rows.groupBy("rec_id").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("length"))
    return rows.join(length.where("length > 0"), "rec_id").select("rec_id", "token", (F.col("w") / F.col("length")).alias("weight"))


def tfidf_cosine(pairs: DataFrame, left: DataFrame, right: DataFrame, tokens_col: str = "title") -> DataFrame:
    """pair_id, sim: cosine of the weighted token vectors; 0 where one has none."""
    frequency = document_frequency(left.unionByName(right), tokens_col)
    a = tfidf(left, frequency, tokens_col).select(F.col("rec_id").alias("id_a"), "token", F.col("weight").alias("w_a"))
    b = tfidf(right, frequency, tokens_col).select(F.col("rec_id").alias("id_b"), "token", F.col("weight").alias("w_b"))
    met = pairs.select("pair_id", "id_a", "id_b").join(a, "id_a").join(b, ["id_b", "token"]).groupBy("pair_id").agg(F.sum(F.col("w_a") * F.col("w_b")).alias("sim"))
    return pairs.select("pair_id").join(met, "pair_id", "left").select("pair_id", F.coalesce("sim", F.lit(0.0)).alias("sim"))


def token_vectors(records: DataFrame, how: str, dims: int = 256, tokens_col: str = "title", seed: int = 42, parts: int = 1) -> DataFrame:
    """rec_id, features (array): hashed (counts by hash, times inverse document frequency), counts (of the ``dims`` most frequent tokens) or word2vec (mean of token vectors, learned in so many parts)."""
    source = {"inputCol": tokens_col, "outputCol": "v"}
    stages = {
        "hashed": lambda: [HashingTF(numFeatures=dims, inputCol=tokens_col, outputCol="tf"), IDF(inputCol="tf", outputCol="v")],
        "counts": lambda: [CountVectorizer(vocabSize=dims, minDF=2, **source)],
        "word2vec": lambda: [Word2Vec(vectorSize=dims, minCount=2, numPartitions=parts, seed=seed, **source)],
    }[how]()
    rows = records.select("rec_id", F.coalesce(tokens_col, F.array().cast("array<string>")).alias(tokens_col))
    return Pipeline(stages=stages).fit(rows).transform(rows).select("rec_id", vector_to_array("v").alias("features"))


def near_vectors(left: DataFrame, right: DataFrame, distance: float, bucket: float = 2.0, tables: int = 6, seed: int = 42) -> DataFrame:
    """id_a, id_b, distance of vectors (id, v array) at most so far apart that share a bucket of a random projection; distances are exact, a few pairs may be missed."""
    a, b = (t.select("id", array_to_vector(F.transform("v", lambda x: x.cast("double"))).alias("x")) for t in (left, right))
    model = BucketedRandomProjectionLSH(inputCol="x", outputCol="h", bucketLength=bucket, numHashTables=tables, seed=seed).fit(a)
    met = model.approxSimilarityJoin(a, b, distance, "distance")
    return met.select(F.col("datasetA.id").alias("id_a"), F.col("datasetB.id").alias("id_b"), "distance")


def label_agreement(vectors: DataFrame, cut_at: float, block_rows: int = 1024) -> DataFrame:
    """tp, fp, fn, tn of all pairs of one bucket: a cosine over cut_at says that two labels agree. vectors: id, bucket, v, label.

    Buckets are dealt into blocks of about so many rows, and every two blocks of a bucket
    meet in one task as matrices, so pairs are counted and never made into rows. As for
    the cosine column, a vector of length zero has cosine 0, and NaN is over any cut. Pairs
    of vectors of different lengths or with a null have no cosine and count as 0; rows without a label take no part.
    """
    rows = vectors.where("id is not null and bucket is not null and label is not null").select("id", "bucket", F.transform("v", lambda x: x.cast("double")).alias("v"), F.col("label").cast("string").alias("label"))
    blocks = F.broadcast(rows.groupBy("bucket").agg(F.ceil(F.count(F.lit(1)) / block_rows).cast("int").alias("n")))
    rows = rows.join(blocks, "bucket").withColumn("own", F.pmod(F.xxhash64("id"), F.col("n")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
    rows = rows.select("bucket", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "id", "v", "label")

    def count(met: pd.DataFrame) -> pd.DataFrame:
        side = [met[met["own"] == met[c].iloc[0]] for c in "ij"]
        ids = [s["id"].to_numpy() for s in side]
        names = [s["label"].to_numpy(dtype=object) for s in side]
        agree = names[0][:, None] == names[1][None]
        once = ids[0][:, None] < ids[1][None] if met["i"].iloc[0] == met["j"].iloc[0] else ids[0][:, None] != ids[1][None]
        sim = np.zeros(agree.shape)
        sizes = [np.array([len(x) if x is not None and not any(y is None for y in x) else -1 for x in s["v"]], dtype=int) for s in side]
        for size in np.intersect1d(*sizes):
            if size > 0:
                at = [np.nonzero(n == size)[0] for n in sizes]
                a, b = (np.array([np.asarray(s["v"].iloc[k], dtype=float) for k in w]) for s, w in zip(side, at, strict=True))
                with np.errstate(all="ignore"):
                    long = np.sqrt((a * a).sum(1))[:, None] * np.sqrt((b * b).sum(1))[None]
                    sim[np.ix_(*at)] = np.where(long == 0, 0.0, (a @ b.T) / long)
        with np.errstate(all="ignore"):
            over = (sim > cut_at) | np.isnan(sim)
        pick = lambda y, t: int(np.count_nonzero(once & (over == y) & (agree == t)))
        return pd.DataFrame({"tp": [pick(True, True)], "fp": [pick(True, False)], "fn": [pick(False, True)], "tn": [pick(False, False)]})

    met = rows.groupBy("bucket", "i", "j").applyInPandas(count, "tp long, fp long, fn long, tn long")
    return met.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("tp", "fp", "fn", "tn")])
