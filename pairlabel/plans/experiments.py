"""The experiments: comparison, sensitivity and scalability, on stand-in workloads from the given tables.

Runs of the staged method are independent workloads, so all runs of an experiment
go through one job: each is a shard with settings of its own.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines as B
from ..operators import easy as E
from ..operators import features as X
from ..operators import infer
from ..operators import metrics as M
from ..operators import workload as W
from ..settings import Settings
from .planner import cut

#: Many labels per round, fits only where the approximation is unsure, curves renewed as evidence grows: our form for larger runs, not the method as described.
FAST = Settings(labels_per_round=10, k=10, fit_above=0.05, refresh=0.01)


@dataclass
class Workload:
    """pairs, incidence and truth (pair_id, truth) of a named workload."""

    name: str
    pairs: DataFrame
    incidence: DataFrame
    truth: DataFrame
    share: float


_built: dict[tuple, Workload] = {}


def build(spark: SparkSession, sf_dir: str, name: str) -> Workload:
    """The named workload; its tables are written once per session."""
    key = (spark.sparkContext.applicationId, id(spark), sf_dir, name)
    if key not in _built:
        _built[key] = _build(spark, sf_dir, name)
    return _built[key]


#: Features beyond the attribute similarities: the balanced workload has edit, Jaro-Winkler and hybrid metrics of the title, the one-table one Jaro-Winkler, all but that one the whole body's longest run.
#: Shared rare tokens of the body (same_attrs) are left out: about sixty a pair.
BODY = {"lcs_attrs": ("title", "body")}
FEATURES = {"W1b": {"metrics": ("jw_title", "edit_title", "hybrid_title"), **BODY}, "W2s": {"metrics": ("jw_title",)}, "W1t": {}}


def _build(spark: SparkSession, sf_dir: str, name: str) -> Workload:
    """W1h (clean truth), W1v (variants count as different), W1b (balanced), W1t (title only: a stress), W2s (one table)."""
    left = cut(W.document_records(W.load(spark, sf_dir, "documents")), "left")
    right = cut(W.corrupt(left), "right")
    records = left.unionByName(right)
    if name == "W2s":
        shift = left.agg(F.coalesce(F.max("rec_id"), F.lit(0)) + 1).first()[0]
        records = left.unionByName(right.withColumn("rec_id", F.col("rec_id") + shift))
        pairs = cut(W.with_similarity(W.compare(W.block_within(records, 200, 3), records, records, source="jaro_winkler"), W.attribute_weights(records)), "pairs")
        own = W.strict_entities(left)
        entities = own.unionByName(own.withColumn("rec_id", F.col("rec_id") + shift))
        sides = (records, records)
    else:
        blocked = W.block_by_tokens(left, right, 60, 1) if name == "W1b" else W.block_by_tokens(left, right)
        pairs = cut(W.with_similarity(W.compare(blocked, left, right), W.attribute_weights(left, right)), "pairs")
        if name == "W1t":
            pairs = pairs.withColumn("sim", F.round("sim_title", 9))
        entities = W.cluster_entities(left) if name in ("W1h", "W1b") else W.strict_entities(left, W.TITLE if name == "W1t" else None)
        sides = (left, right)
    truth = cut(W.truth(pairs, entities), "truth")
    if name == "W1b":  # thin the false pairs to a true share of 45%
        n1, n = truth.agg(F.coalesce(F.sum("truth"), F.lit(0)), F.count(F.lit(1))).first()
        rate = min(1.0, n1 * 55 / 45 / max(1, n - n1))
        truth = truth.where((F.col("truth") == 1) | (W.hash_order("pair_id") < F.lit(int((1 << 60) * rate))))
        pairs = cut(pairs.join(truth.select("pair_id"), "pair_id", "left_semi"), "thinned")
    cols = ("sim_title",) if name == "W1t" else W.PARTS
    share = B.cluster_pairs_fixed(pairs, cols, 25 if name == "W2s" else 10).agg(F.coalesce(F.avg("label"), F.lit(0.0))).first()[0]
    further = FEATURES.get(name, BODY)
    whole = W.with_bodies(pairs, *sides) if "lcs_attrs" in further else pairs
    return Workload(name, pairs, cut(X.incidence(whole, records, **further), "incidence"), truth, share)


@dataclass
class Run:
    workload: Workload
    settings: Settings
    ratio: float = 0.30
    label: str = ""


def label_many(runs: list[Run]) -> DataFrame:
    """run (number), the round log of each run, and the CPU seconds that it took."""
    table = None
    for k, r in enumerate(runs):
        w = r.workload
        easy = cut(E.easy_by_ratio(w.pairs, r.ratio, w.share), "easy")
        one = infer._one_table(w.pairs, X.informative(w.incidence, easy), easy, None).withColumn("shard", F.lit(k).cast("long"))
        table = one if table is None else table.unionAll(one)
    settings = [r.settings for r in runs]
    names = [c.split()[0] for c in infer.LOG.split(", ")]

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        k = int(rows["shard"].iloc[0])
        base = rows["feature_id"].isna().to_numpy()
        own = rows[base]
        kernel = infer.Kernel(own["pair_id"].to_numpy(), own["x"].to_numpy(dtype=float), rows[~base], settings[k])
        known = own[own["label"].notna()]
        began = time.process_time()
        out = pd.DataFrame(kernel.run(dict(zip(known["pair_id"].tolist(), known["label"].astype(int).tolist(), strict=True))), columns=names)
        for c in ("support", "p_approx", "p", "h"):
            out[c] = out[c].astype(float)
        out["run"], out["seconds"] = k, time.process_time() - began
        return out

    return table.repartition(len(runs), "shard").groupBy("shard").applyInPandas(run, f"{infer.LOG}, run int, seconds double")


def scored(runs: list[Run]) -> DataFrame:
    """workload, setting, precision, recall, f1, flips of each run."""
    log = cut(label_many(runs), "logs")
    out = None
    for k, r in enumerate(runs):
        own = log.where(F.col("run") == k)
        flips = own.agg(F.count_if(F.col("flipped")).alias("flips"))
        one = M.quality(own, r.workload.truth).join(F.broadcast(flips)).select(F.lit(r.workload.name).alias("workload"), F.lit(r.label).alias("setting"), "precision", "recall", "f1", "flips")
        out = one if out is None else out.unionAll(one)
    return out


def comparison(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("W1b", "W1v", "W2s"), runs: int = 10, settings: Settings = Settings(), shares: tuple[float, ...] = (0.1, 0.2, 0.3)) -> DataFrame:
    """method, workload, precision, recall, f1: staged labeling, rule, clustering, and the means over runs of SVM and perceptron at each share."""
    ws = [build(spark, sf_dir, n) for n in names]
    out = scored([Run(w, settings, label="staged") for w in ws]).select("workload", F.col("setting").alias("method"), "precision", "recall", "f1")
    for w in ws:
        for method, labels in (("rule", B.rule_pairs(w.pairs, w.share)), ("clustering", B.cluster_pairs_fixed(w.pairs, rounds=25 if w.name == "W2s" else 10))):
            out = out.unionByName(M.quality(labels, w.truth).select(F.lit(w.name).alias("workload"), F.lit(method).alias("method"), "precision", "recall", "f1"))
        for method in ("svm", "mlp"):
            got = B.supervised_runs(w.pairs, w.truth, method, shares, runs).groupBy("share").agg(*[F.avg(c).alias(c) for c in ("precision", "recall", "f1")])
            name = F.concat(F.lit(method + " "), (F.col("share") * 100).cast("int").cast("string"), F.lit("%"))
            out = out.unionByName(got.select(F.lit(w.name).alias("workload"), name.alias("method"), "precision", "recall", "f1"))
    return out


def sensitivity(spark: SparkSession, sf_dir: str, what: str, values: tuple, names: tuple[str, ...] = ("W1b", "W2s"), settings: Settings = Settings()) -> DataFrame:
    """The staged method over values of one parameter: easy_ratio, m, k, interval_cap, labels_per_round or any other setting."""
    runs = []
    for w in (build(spark, sf_dir, n) for n in names):
        for v in values:
            if what == "easy_ratio":
                runs.append(Run(w, settings, v, str(v)))
            else:
                runs.append(Run(w, replace(settings, **{what: v}), 0.30, str(v)))
    return scored(runs)


def scalability(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (10_000, 20_000, 30_000, 40_000), settings: Settings = Settings(m=2000, k=1, interval_cap=50), ratio: float = 0.5) -> DataFrame:
    """size, seconds, fits, multiple: CPU time of the staged method on one workload cut to several sizes with its match share kept. The sizes run side by side."""
    w = build(spark, sf_dir, "W1h")
    runs, counts = [], {}
    for k, n in enumerate(sizes):
        pairs = cut(W.resize(w.pairs, w.truth, n).drop("truth"), "pairs")
        part = Workload(w.name, pairs, cut(w.incidence.join(pairs.select("pair_id"), "pair_id", "left_semi"), "incidence"), w.truth, w.share)
        runs.append(Run(part, settings, ratio))
        counts[k] = pairs.count()
    took = label_many(runs).groupBy("run").agg(F.max("seconds").alias("seconds"), F.sum("fits").alias("fits"))
    named = F.element_at(F.create_map(*[F.lit(x) for kv in counts.items() for x in kv]), F.col("run"))
    return M.cost_multiple(took.select(named.cast("long").alias("size"), "seconds", "fits"))
