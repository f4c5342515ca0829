"""Queries for whole runs of the method and for the experiments; SQL cannot express these, tests hold them against numpy twins."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import similarity as S
from ..operators import baselines as B
from ..operators import containment
from ..operators import easy as E
from ..operators import features as X
from ..operators import graph as G
from ..operators import infer
from ..operators import metrics as M
from ..operators import vectors as V
from ..operators import workload as W
from ..plans import experiments as P
from ..plans.planner import cut
from ..settings import Settings
from . import base as Q
from . import method
from .method import QUERIES as _ALL
from .method import rounded

QUERIES: dict = {}


def query(f):
    assert f.__name__ not in _ALL
    QUERIES[f.__name__] = f
    return f


def _easy(spark, d) -> DataFrame:
    return Q.kept(spark, d, "easy30", lambda: E.easy_by_ratio(Q.pairs(spark, d), 0.3, Q.share(spark, d)))


def _incidence(spark, d) -> DataFrame:
    return Q.kept(spark, d, "informative", lambda: X.informative(Q.incidence(spark, d), _easy(spark, d)))


def staged(spark, d, settings: Settings = P.FAST, easy: DataFrame | None = None) -> DataFrame:
    return infer.label_kernel(Q.pairs(spark, d), _incidence(spark, d), _easy(spark, d) if easy is None else easy, settings)


@query
def i19_fit(spark, d):
    """Likelihood fits of a round's k targets on their capped subgraphs."""
    targets = method.targets(spark, d)
    labels = Q.easy(spark, d)
    weight = G.class_weight(labels)
    curves = G.fit_curves(G.feature_stats(Q.incidence(spark, d), labels), weight, Settings())
    evidence = G.capped(G.evidence_of(Q.incidence(spark, d), labels, targets), 200, salts=8)
    return rounded(infer.fit_targets(G.own_features(Q.incidence(spark, d), targets), evidence, curves, weight.first()["w"], Settings()), 4)


@query
def i20_exact(spark, d):
    """The exact mode, which suits small workloads: joint fits of all features on all evidence of one undivided graph, 50 labels a fit."""
    return infer.label_kernel(Q.pairs(spark, d), _incidence(spark, d), _easy(spark, d), Settings(labels_per_round=50), exact=True)


@query
def i22_scalable(spark, d):
    """The method as described: in every round fresh curves, all k candidates fitted, and one label."""
    return staged(spark, d, Settings())


@query
def i22_fast(spark, d):
    """Ours, for larger runs: ten labels a round, fits only where the approximation is unsure, curves renewed by growth of evidence."""
    return staged(spark, d, P.FAST)


@query
def i22_rounds(spark, d):
    """The same rounds as Spark jobs over tables of any size: the best supported, of these the surest, all of them fitted; an eighth of the pairs are labeled at a time."""
    n = max(1, Q.pairs(spark, d).count() // 8)
    return infer.label_rounds(Q.pairs(spark, d), _incidence(spark, d), _easy(spark, d), Settings(labels_per_round=n, k=n, m=max(2000, 2 * n)))


@query
def i23_no_fit(spark, d):
    return staged(spark, d, replace(P.FAST, use_mle=False))


@query
def i24_all_m(spark, d):
    return staged(spark, d, replace(P.FAST, m=None))


@query
def i25_batch(spark, d):
    return staged(spark, d, replace(P.FAST, labels_per_round=100, k=100, h_max=0.5))


@query
def i26_seeded(spark, d):
    """A tenth of the unlabeled pairs of middling similarity come labeled."""
    truth = Q.strict_truth(spark, d)
    seeds = Q.pairs(spark, d).where((F.col("sim") > 0.4) & (F.col("sim") < 0.6) & (F.col("pair_id") % 10 == 3)).join(truth, "pair_id").select("pair_id", F.col("truth").alias("label"))
    easy = _easy(spark, d).join(seeds, "pair_id", "left_anti").unionByName(seeds)
    return staged(spark, d, P.FAST, easy)


@query
def i27_items(spark, d):
    """Another binary task: documents of good quality, from text statistics, with extremes of one statistic as easy labels."""
    docs = W.load(spark, d, "documents")
    t = S.tokens(F.col("text"))
    letters = F.length(F.regexp_replace(F.coalesce("text", F.lit("")), r"[^\p{L} ]", "")) / F.greatest(F.length(F.coalesce("text", F.lit(""))), F.lit(1))
    items = docs.select(F.col("doc_id").alias("item_id"), letters.alias("score"), (F.size(F.array_distinct(t)) / F.greatest(F.size(t), F.lit(1))).alias("distinct_share"), F.least(F.size(t) / 1000, F.lit(1.0)).alias("size"))
    tall = items.unpivot("item_id", ["score", "distinct_share", "size"], "attr", "x")
    inc = tall.select("item_id", X.feature_id(F.lit("attr"), F.col("attr"), F.lit("")).alias("feature_id"), "x")
    easy = items.where("score >= 0.97 or score <= 0.85").select("item_id", (F.col("score") >= 0.97).cast("int").alias("label"))
    return infer.label_items(items.select("item_id", "score"), inc, easy, P.FAST)


@query
def c4_svm(spark, d):
    """Ten runs at each share of training data."""
    return B.supervised_runs(Q.pairs(spark, d), Q.cluster_truth(spark, d), "svm")


@query
def c5_mlp(spark, d):
    """Ten runs at each share of training data, of which a twentieth of all pairs validates."""
    return B.supervised_runs(Q.pairs(spark, d), Q.cluster_truth(spark, d), "mlp")


@query
def c4_svm_ml(spark, d):
    """One run of the classifier for tables of any size."""
    return B.svm_pairs(Q.pairs(spark, d), Q.cluster_truth(spark, d), 0.1, runs=1)


@query
def c5_mlp_ml(spark, d):
    return B.mlp_pairs(Q.pairs(spark, d), Q.cluster_truth(spark, d), 0.15, 0.05, runs=1)


@query
def x8_comparison(spark, d):
    """All methods on the balanced and the one-table workload; ten runs of each supervised method at each share. bench/experiments.py has all workloads."""
    return P.comparison(spark, d, ("W1b", "W2s"))


@query
def x9_monotonicity(spark, d):
    out = None
    for name, truth in (("W1h", Q.cluster_truth(spark, d)), ("W1v", Q.strict_truth(spark, d))):
        one = M.precision_by_interval(Q.pairs(spark, d), truth).withColumn("workload", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


@query
def x9_more(spark, d):
    """The same on the balanced and the one-table workload."""
    out = None
    for name in ("W1b", "W2s"):
        w = P.build(spark, d, name)
        one = M.precision_by_interval(w.pairs, w.truth).withColumn("workload", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


@query
def x10_ratio(spark, d):
    return P.sensitivity(spark, d, "easy_ratio", (0.3, 0.4, 0.5), settings=P.FAST)


@query
def x11_m(spark, d):
    return P.sensitivity(spark, d, "m", (500, 1000, 2000), settings=P.FAST)


@query
def x12_k(spark, d):
    """As described, one label a round, on the one-table workload; bench/experiments.py has all."""
    return P.sensitivity(spark, d, "k", (1, 5, 10), ("W2s",))


@query
def x13_cap(spark, d):
    return P.sensitivity(spark, d, "interval_cap", (50, 100, 200), settings=P.FAST)


@query
def x14_scalability(spark, d):
    """Cost multiples at four sizes, up to 40,000 pairs where there are so many."""
    n = min(40_000, Q.pairs(spark, d).count())
    return P.scalability(spark, d, tuple(n * k // 4 for k in (1, 2, 3, 4)))


@query
def x15_flips(spark, d):
    """Of the method as described."""
    return M.flip_rate(staged(spark, d, Settings()).where(~F.col("easy")))


@query
def x16_batch(spark, d):
    """Ours: what labeling many pairs per round costs in accuracy."""
    return P.sensitivity(spark, d, "labels_per_round", (1, 10, 100), settings=P.FAST)


@query
def x2_stress(spark, d):
    """Title-only similarity, whose easy labels are impure: expected to do badly."""
    return P.scored([P.Run(P.build(spark, d, "W1t"), P.FAST, label="title only")])


@query
def x3_natural(spark, d):
    """Natural near copies: documents paired within the table, truth by the similarity of their first tokens."""
    left = Q.left(spark, d)
    pairs = W.compare(W.block_within(left, 20, 1), left, left)
    pairs = W.with_similarity(pairs, W.attribute_weights(left))
    pairs = cut(pairs, "pairs")
    truth = cut(W.truth(pairs, W.cluster_entities(left)), "truth")
    w = P.Workload("W3", pairs, cut(X.incidence(pairs, left), "incidence"), truth, B.match_share(pairs))
    return P.scored([P.Run(w, replace(P.FAST, labels_per_round=50, k=50), label="natural")])


@query
def x4_containment(spark, d):
    """Benchmark passages in documents that share any token: share of a passage's tokens that a document has, with the longest common run; both texts whole."""
    return containment.contained(W.load(spark, d, "benchmark"), W.load(spark, d, "documents"))


@query
def x7_control(spark, d):
    """Negative control: vectors whose labels say nothing about their cosine."""
    e = W.load(spark, d, "embeddings").select("vec_id", "embedding", "label")
    def side(k: int):
        signed = F.transform("embedding", lambda x, i: F.when((i * 7 + k * 13) % 5 < 2, x).otherwise(-x).cast("double"))
        return F.aggregate(signed, F.lit(0.0), lambda s, v: s + v) > 0

    planes = [side(k) for k in range(6)]
    e = e.withColumn("bucket", F.concat(*[p.cast("int").cast("string") for p in planes]))
    counts = V.label_agreement(e.select(F.col("vec_id").alias("id"), "bucket", F.col("embedding").alias("v"), "label"), 0.2)
    return M.quality_of(counts)


#: Runs by positions: equal tokens on one diagonal, numbered without gaps.
_BY_BIN = "SELECT CAST(least(floor(sim * 10), 9) AS INT) AS bin, count(*) AS n, CAST(sum(truth) AS BIGINT) AS matches, sum(truth) / CAST(count(*) AS DOUBLE) AS precision, '{0}' AS workload FROM pairs JOIN {1} USING (pair_id) GROUP BY 1"
SQL = {
    "x9_monotonicity": f"""{method.CLUSTER}, {Q.BLOCKED}, {Q.COMPARED}, {Q.STRICT}, components AS (SELECT node AS rec_id, min(root) AS entity_id FROM walk GROUP BY node),
same AS (SELECT pair_id, CAST(ca.entity_id = cb.entity_id AS INT) AS truth FROM pairs JOIN components ca ON ca.rec_id = id_a JOIN components cb ON cb.rec_id = id_b)
{_BY_BIN.format('W1h', 'same')} UNION ALL {_BY_BIN.format('W1v', 'truth')}""",
    "x4_containment": f"""
WITH p AS MATERIALIZED (SELECT item_id, {Q.TOKENS} AS t FROM benchmark), q AS MATERIALIZED (SELECT doc_id, {Q.TOKENS} AS t FROM documents),
a AS MATERIALIZED (SELECT item_id, unnest(t) AS w, generate_subscripts(t, 1) AS i FROM p), b AS MATERIALIZED (SELECT doc_id, unnest(t) AS w, generate_subscripts(t, 1) AS j FROM q),
met AS MATERIALIZED (SELECT item_id, doc_id, w, i, i - j AS diag FROM a JOIN b USING (w)),
islands AS (SELECT item_id, doc_id, diag, i - row_number() OVER (PARTITION BY item_id, doc_id, diag ORDER BY i) AS island FROM met),
runs AS (SELECT item_id, doc_id, max(n) AS run FROM (SELECT item_id, doc_id, count(*) AS n FROM islands GROUP BY item_id, doc_id, diag, island) GROUP BY item_id, doc_id),
shared AS (SELECT item_id, doc_id, count(DISTINCT w) AS n FROM met GROUP BY item_id, doc_id)
SELECT item_id, doc_id, round(n / CAST(len(list_distinct(t)) AS DOUBLE), 6) AS contained, CAST(run AS INT) AS run
FROM shared JOIN runs USING (item_id, doc_id) JOIN p USING (item_id)""",
}
