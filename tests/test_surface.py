"""Streams, sources, sinks, transforms and the measures of runs."""

import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from pairlabel.functions import influence as I
from pairlabel.functions.sql import wls_curve
from pairlabel.operators import easy as E
from pairlabel.operators import features as X
from pairlabel.operators import infer
from pairlabel.operators import metrics as M
from pairlabel.operators import vectors as V
from pairlabel.operators import workload as W
from pairlabel.settings import Settings
from pairlabel.sources import io
from pairlabel.streaming import streams as T


@pytest.fixture
def arriving(spark, tmp_path):
    """Three files, read one by one in the order of their writing."""
    batches = [[(1, 1, "2024-01-01 10:00:00"), (2, 2, "2024-01-01 12:00:00")], [(3, 1, "2024-01-01 11:30:00"), (4, 1, "2024-01-01 09:00:00"), (5, 2, None)], [(6, 2, "2024-01-01 11:00:01"), (7, 2, "2024-01-02 00:00:00")]]
    path = str(tmp_path / "in")
    for k, rows in enumerate(batches):
        df = spark.createDataFrame(rows, "event_id long, user_id long, ts string").withColumn("ts", F.col("ts").cast("timestamp")).withColumn("value", F.col("event_id") * 1.0)
        df.coalesce(1).write.mode("append").parquet(path)
        for f in (tmp_path / "in").glob("*.parquet"):
            if f.stat().st_mtime > 1_600_000_000:
                os.utime(f, (1_500_000_000 + 10 * k,) * 2)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def ids(df, c="event_id"):
    return sorted(r[c] for r in df.collect())


def test_late_rows(arriving):
    on_time, late = T.late_split(arriving, 3600)
    assert ids(late) == [4] and ids(on_time) == [1, 2, 3, 5, 6, 7]
    on_time, late = T.late_split(arriving, 0)
    assert ids(late) == [3, 4, 6]


def test_stateful_counts(arriving):
    got = T.run_once(T.user_runs(arriving), "update", ["user_id"])
    assert sorted(map(tuple, got.collect())) == [(1, 3, 8.0), (2, 4, 20.0)]


def test_repeated_batch_leaves_no_copy(spark, tmp_path):
    write = T.idempotent_sink(str(tmp_path))
    for number in (0, 1, 1, 0):
        write(spark.range(5), number)
    assert spark.read.parquet(f"{tmp_path}/*").count() == 10


def test_records_with_broken_rows(spark, tmp_path):
    schema = spark.createDataFrame([(1, 1.5)], "id long, x double").schema
    (tmp_path / "a.csv").write_text("1,2.5\ntwo,3\n3,4.5\n")
    (tmp_path / "a.json").write_text('{"id": 1, "x": 2.5}\n{"id": \n{"id": 3, "x": 4.5}\n')
    for f in ("csv", "json"):
        path = str(tmp_path / f"a.{f}")
        assert ids(io.read_records(spark, path, f, schema, "drop"), "id") == [1, 3]
        kept = io.read_records(spark, path, f, schema).cache()
        assert kept.count() == 3 and kept.where("_broken is not null").count() == 1
        with pytest.raises(Exception, match="(?i)malformed|parse"):
            io.read_records(spark, path, f, schema, "fail").collect()
    assert io.read_records(spark, str(tmp_path / "a.csv"), "text", schema).count() == 3


def test_labels_are_appended_by_round(spark, tmp_path):
    pairs = spark.range(6).withColumnRenamed("id", "pair_id")
    log = pairs.where("pair_id < 4").select("pair_id", (F.col("pair_id") % 2).alias("round"), F.lit(1).alias("label"))
    path = str(tmp_path / "log")
    io.write_labels(log.where("round = 0"), path)
    io.write_labels(log.where("round = 1"), path)
    back = spark.read.parquet(path)
    assert back.count() == 4 and ids(io.unlabeled(pairs, back), "pair_id") == [4, 5]


def test_bucketed_tables_join_without_shuffle(spark):
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        for t in ("bucketed_a", "bucketed_b"):
            io.write_bucketed(spark.range(1000).withColumnRenamed("id", "k"), t, "k", 4)
        plan = spark.table("bucketed_a").join(spark.table("bucketed_b"), "k")
        assert plan.count() == 1000 and "Exchange" not in plan._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        for t in ("bucketed_a", "bucketed_b"):
            spark.sql(f"DROP TABLE IF EXISTS {t}")


def test_flips_and_cost(spark):
    log = spark.createDataFrame([(k, k % 4 == 0) for k in range(20)], "round int, flipped boolean")
    got = {r.tenth: (r.labels, r.flips) for r in M.flip_rate(log).collect()}
    assert len(got) == 10 and sum(n for n, _ in got.values()) == 20 and sum(f for _, f in got.values()) == 5
    times = spark.createDataFrame([(20, 5.0), (10, 2.0), (40, 11.0)], "size long, seconds double")
    assert {r["size"]: r["multiple"] for r in M.cost_multiple(times).collect()} == {10: 1.0, 20: 2.5, 40: 5.5}


def test_curve_aggregate(spark):
    rng = np.random.default_rng(2)
    x, y = np.concatenate([rng.uniform(0, 0.5, 12), rng.uniform(0.4, 1, 5)]), np.repeat([0, 1], [12, 5])
    rows = [(1, float(a), int(b)) for a, b in zip(x, y, strict=True)] + [(1, None, 1), (2, 0.5, 0), (2, 0.6, 0)]
    df = spark.createDataFrame(rows, "f int, x double, label int").withColumn("w", F.lit(2.4))
    got = {r.f: r.c for r in df.groupBy("f").agg(wls_curve("x", "label", "w").alias("c")).collect()}
    want = I.curves_np(np.array([[12, x[:12].sum(), (x[:12] ** 2).sum(), 5, x[12:].sum(), (x[12:] ** 2).sum()]]), 2.4, Settings())
    assert got[1] == pytest.approx([want[c][0] for c in ("tau", "alpha", "sigma")]) and got[2] is None


def test_transforms(spark):
    recs = spark.createDataFrame([(1, ["a", "b"]), (2, ["a", "c", "c"]), (3, ["a"]), (4, None)], "rec_id long, title array<string>")
    sims = spark.createDataFrame([(1, 1, 1), (2, 1, 2), (3, 2, 2), (4, 3, 4)], "pair_id long, id_a long, id_b long")
    got = {r.pair_id: r.sim for r in V.tfidf_cosine(sims, recs, recs).collect()}
    ln = np.log
    u, v = np.array([ln(8 / 6), ln(8 / 2), 0]), np.array([ln(8 / 6), 0, 2 * ln(8 / 2)])
    assert got == pytest.approx({1: 1.0, 2: float(u @ v / np.linalg.norm(u) / np.linalg.norm(v)), 3: 1.0, 4: 0.0})
    for how in ("hashed", "counts", "word2vec"):
        rows = V.token_vectors(recs, how, 4).collect()
        assert len(rows) == 4 and all(np.isfinite(r.features).all() for r in rows)
    flat = spark.createDataFrame([(1, 0.0, 5.0), (2, 1.0, 5.0)], "pair_id long, a double, b double")
    assert sorted(map(tuple, V.scaled(flat, ("a", "b"), "range").collect())) == [(1, 0.0, 0.0), (2, 1.0, 0.0)]
    assert V.scaled(flat, ("a", "b")).where("pair_id = 2").first().a == pytest.approx(0.5**0.5)


def test_near_vectors_against_all_pairs(spark):
    rng = np.random.default_rng(3)
    v = rng.normal(size=(120, 6))
    v[60:] = v[:60] + rng.normal(size=(60, 6)) * 0.05
    df = spark.createDataFrame([(k, x.tolist()) for k, x in enumerate(v)], "id long, v array<double>")
    got = {(r.id_a, r.id_b): r.distance for r in V.near_vectors(df, df, 0.5).where("id_a < id_b").collect()}
    want = {(a, b): float(np.linalg.norm(v[a] - v[b])) for a in range(120) for b in range(a + 1, 120) if np.linalg.norm(v[a] - v[b]) <= 0.5}
    assert set(got) <= set(want) and len(got) >= 0.95 * len(want)
    assert all(got[k] == pytest.approx(want[k]) for k in got)


def test_two_small_tables_end_to_end(spark):
    """Five records in two tables: blocked, compared, labeled from the extremes, and the rest by inference."""
    rec = "rec_id long, title array<string>, body array<string>, source string, n_chars double, words array<string>"
    one = lambda i, title, source, n: (i, title.split(), title.split()[::-1], source, float(n), title.split() * 2)
    a = spark.createDataFrame([one(1, "tidal wetlands of the northern coast", "j1", 120), one(2, "spectral clustering with sparse graphs", "j2", 80)], rec)
    b = spark.createDataFrame([one(1, "tidal wetlands of the northern coast", "j1", 120), one(2, "spectral clustering on sparse graphs", "j2", 82), one(3, "wetlands of the tropics", "j3", 300)], rec)
    pairs = W.with_similarity(W.compare(W.block_by_tokens(a, b), a, b), W.attribute_weights(a, b))
    got = {(r.id_a, r.id_b): r for r in pairs.collect()}
    assert set(got) == {(1, 1), (2, 2), (1, 3)} and got[1, 1].sim == pytest.approx(1.0) and got[1, 3].sim < got[2, 2].sim < 1
    easy = E.easy_by_bounds(pairs, got[1, 3].sim, 0.99)
    inc = X.incidence(pairs, a.unionByName(b), idf_min=0.0)
    log = {r.pair_id: r for r in infer.label_kernel(pairs, X.informative(inc, easy), easy).collect()}
    assert len(log) == 3 and [log[got[k].pair_id].label for k in ((1, 1), (1, 3), (2, 2))] == [1, 0, 1]
