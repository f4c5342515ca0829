"""The methods against numpy twins, golden numbers, invariants and limits."""

import hashlib
import math
from dataclasses import replace

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from pairlabel.functions import influence as I
from pairlabel.functions import similarity as S
from pairlabel.operators import baselines as B
from pairlabel.operators import easy as E
from pairlabel.operators import features as X
from pairlabel.operators import graph as G
from pairlabel.operators import infer
from pairlabel.operators import metrics as M
from pairlabel.operators import workload as W
from pairlabel.operators.fit import fit, loss, project
from pairlabel.plans import planner
from pairlabel.queries import base as Q
from pairlabel.settings import Settings

# the numeric round of FIXTURES.md
NON, MATCH = [0.05, 0.10, 0.15, 0.20, 0.25, 0.40], [0.70, 0.85, 0.95]
GOLD_CURVES = {"dense": (12.860490, 0.512500, 1.688890, 0.405556, 0.932222), "tok": (13.625263, 0.579250, 1.901993, 0.587500, 0.426875)}
GOLD_PAIRS = {101: (0.818266, 0.974628, 0.726041, 0.847088), 102: (0.703309, -0.113061, 0.471765, 0.997698), 103: (0.813294, -4.386289, 0.012294, 0.095642)}


@pytest.fixture(scope="module")
def golden(spark):
    ev = [(k, x, 0) for k, x in enumerate(NON)] + [(10 + k, x, 1) for k, x in enumerate(MATCH)]
    inc = [(i, 1, x) for i, x, _ in ev] + [(i, 2, x) for i, x, _ in ev if x in (0.15, 0.40, 0.85, 0.95)]
    inc += [(101, 1, 0.6), (101, 2, 0.6), (102, 1, 0.5), (103, 1, 0.3), (103, 2, 0.3)]
    labels = spark.createDataFrame([(i, y) for i, _, y in ev], "pair_id long, label int")
    return spark.createDataFrame(inc, "pair_id long, feature_id long, x double"), labels


def test_golden_round(golden):
    inc, labels = golden
    weight = G.class_weight(labels)
    assert weight.first()["w"] == 2.0
    curves = G.fit_curves(G.feature_stats(inc, labels), weight, Settings())
    got = {r.feature_id: r for r in curves.collect()}
    for f, name in ((1, "dense"), (2, "tok")):
        r = got[f]
        assert [r.tau, r.alpha, r.sigma, r.xbar, r.dev] == pytest.approx(GOLD_CURVES[name], abs=2e-5)
    entries = G.with_confidence(inc.where("pair_id > 100"), curves, Settings())
    theta = {(r.pair_id, r.feature_id): 2 * r.theta - 1 for r in entries.collect()}
    assert theta[101, 1] == pytest.approx(0.401710, abs=1e-5) and theta[103, 2] == pytest.approx(0.295593, abs=1e-5)
    sup = {r.pair_id: r.support for r in G.support(entries).collect()}
    approx = {r.pair_id: r for r in G.approx_probability(entries).collect()}
    for i, (s, z, p, h) in GOLD_PAIRS.items():
        assert sup[i] == pytest.approx(s, abs=1e-5)
        assert [approx[i].z, approx[i].p, approx[i].h] == pytest.approx([z, p, h], abs=1e-4)
    top = G.top_support(G.support(entries), 2)
    assert {r.pair_id for r in top.collect()} == {101, 103}
    assert G.top_certain(G.approx_probability(entries.join(top.select("pair_id"), "pair_id", "left_semi")), 1).first().pair_id == 103


def test_central_t():
    known = [(12.706, 1, 0.95), (4.303, 2, 0.95), (2.228, 10, 0.95), (1.96, 100_000, 0.95), (0.67449, 1e6, 0.5)]
    for q, dof, p in known:
        assert I.central_t_np(np.array([q]), np.array([dof]))[0] == pytest.approx(p, abs=1e-4)


def test_central_t_column(spark):
    rows = [(q, float(v)) for q in (0.1, 1.0, 3.0, 30.0) for v in (1, 2, 5, 60, 4000)]
    df = spark.createDataFrame(rows, "q double, v double").withColumn("p", I.central_t(F.col("q"), F.col("v")))
    for r in df.collect():
        assert r.p == pytest.approx(I.central_t_np(np.array([r.q]), np.array([r.v]))[0], abs=1e-9)


def test_six_sums_equal_least_squares():
    rng = np.random.default_rng(0)
    x, y = np.concatenate([rng.uniform(0, 0.6, 30), rng.uniform(0.3, 1, 12)]), np.repeat([0, 1], [30, 12])
    w, z = 30 / 12, Settings().label_logit
    stats = np.array([[30, x[:30].sum(), (x[:30] ** 2).sum(), 12, x[30:].sum(), (x[30:] ** 2).sum()]])
    c = I.curves_np(stats, w, Settings())
    a = np.column_stack([x, np.ones(42)]) * np.sqrt(np.where(y, w, 1))[:, None]
    slope, icpt = np.linalg.lstsq(a, np.where(y, z, -z) * np.sqrt(np.where(y, w, 1)), rcond=None)[0]
    assert c["tau"][0] == pytest.approx(slope) and c["alpha"][0] == pytest.approx(-icpt / slope)
    assert c["sigma"][0] ** 2 == pytest.approx(((np.where(y, z, -z) - slope * x - icpt) ** 2).sum() / 40)


def test_degenerate_features_are_inactive():
    stats = np.array([[5, 1.0, 0.3, 0, 0, 0], [1, 0.1, 0.01, 1, 0.9, 0.81], [3, 2.4, 2.0, 3, 0.6, 0.2], [3, 1.5, 0.75, 3, 1.5, 0.75], [0, 0, 0, 0, 0, 0]])
    assert not I.curves_np(stats, 1.0, Settings())["active"].any()


def test_fit_reaches_the_least_loss():
    rng = np.random.default_rng(1)
    x = np.concatenate([rng.uniform(0, 0.6, 40), rng.uniform(0.4, 1, 20)])
    y = np.repeat([0, 1], [40, 20])
    row, col, theta = np.arange(60), np.zeros(60, int), np.full(60, 0.8)
    lo, hi = np.array([x[:40].mean()]), np.array([x[40:].mean()])
    alpha, tau, _ = fit(row, col, theta, x, y, lo, hi, match_weight=2.0, steps=2000)
    best = min(loss(row, col, theta, x, y, np.array([a]), np.array([t]), 2.0) for a in np.linspace(lo[0], hi[0], 60) for t in np.linspace(0, 20, 81))
    assert loss(row, col, theta, x, y, alpha, tau, 2.0) <= best + 1e-4
    assert lo[0] - 1e-9 <= alpha[0] <= hi[0] + 1e-9 and 0 <= tau[0] <= 20 + 1e-9
    p, q = project(np.array([-1.0, 30.0, 5.0]), np.array([2.0, 10.0, 6.0]), 20.0)
    assert p.tolist() == [0, 20, 5] and q.tolist() == [2, 0, 6]


def test_similarities(spark):
    rows = [(["a", "b", "c"], ["b", "c", "d"], "kitten", "sitting", 10.0, 8.0), ([], ["a"], "", "x", None, 1.0), (None, None, None, None, 0.0, 0.0), (["x", "a", "b", "y", "a"], ["a", "b", "y", "x"], "dwayne", "duane", -1.0, 1.0)]
    df = spark.createDataFrame(rows, "a array<string>, b array<string>, s string, t string, u double, v double")
    a, b = F.coalesce("a", F.array().cast("array<string>")), F.coalesce("b", F.array().cast("array<string>"))
    got = df.select(S.jaccard(F.col("a"), F.col("b")).alias("j"), S.edit_sim(F.col("s"), F.col("t")).alias("e"), S.number_sim(F.col("u"), F.col("v")).alias("n"), S.lcs_tokens(a, b).alias("r"), S.jaro("s", "t").alias("ja"), S.jaro_winkler("s", "t").alias("jw")).collect()
    assert [r.j for r in got] == [0.5, 0.0, 0.0, 1.0]
    assert got[0].e == pytest.approx(1 - 3 / 7) and got[1].e == 0 and got[2].e == 0
    assert [r.n for r in got] == pytest.approx([0.8, 0.0, 1.0, 0.0])
    assert [r.r for r in got] == [2, 0, 0, 3]
    assert got[3].ja == pytest.approx(0.8222, abs=1e-4) and got[3].jw == pytest.approx(0.84, abs=1e-4)
    assert S.jaro_winkler_value("abxxxxxx", "abyyyyyy") == pytest.approx(0.5)
    assert spark.range(1).select(I.entropy(F.lit(0.5)).alias("a"), I.entropy(F.lit(0.0)).alias("b"), I.logistic(F.lit(-800.0)).alias("c"), I.logistic(F.lit(800.0)).alias("d")).first()[:] == pytest.approx([1.0, 0.0, 0.0, 1.0], abs=1e-12)


def test_workload_has_the_measured_size(spark, sf):
    pairs = Q.pairs(spark, sf)
    assert pairs.count() == 1981
    assert Q.cluster_truth(spark, sf).where("truth = 1").count() == 235  # by whole texts; SQL says the same
    assert Q.strict_truth(spark, sf).where("truth = 1").count() == 208


@pytest.fixture(scope="module")
def prepared(spark, sf):
    pairs = Q.pairs(spark, sf)
    share = B.match_share(pairs)
    easy = E.easy_by_ratio(pairs, 0.3, share).persist()
    return pairs, X.informative(Q.incidence(spark, sf), easy).persist(), easy, share


def test_staged_labeling_beats_the_unsupervised_baselines(spark, sf, prepared):
    pairs, inc, easy, share = prepared
    truth = Q.cluster_truth(spark, sf)
    log = infer.label_kernel(pairs, inc, easy, Settings()).persist()
    assert log.count() == pairs.count() == log.select("pair_id").distinct().count()
    kept = log.where("easy").select("pair_id", "label").exceptAll(easy.select("pair_id", F.col("label").cast("int")))
    assert kept.count() == 0
    staged = M.quality(log, truth).first()["f1"]
    rule, cluster = M.quality(B.rule_pairs(pairs, share), truth).first()["f1"], M.quality(B.cluster_pairs_fixed(pairs), truth).first()["f1"]
    assert staged > rule > cluster and staged > 0.95
    assert rule == pytest.approx(0.926, abs=0.005) and cluster == pytest.approx(0.742, abs=0.005)


@pytest.fixture(scope="module")
def small(prepared):
    """About 150 pairs in hash order, as pandas and Spark tables."""
    pairs, inc, easy, _ = prepared
    few = pairs.select("pair_id", "sim").where("pair_id * 48271 % 2147483647 % 13 = 0").persist()
    some = lambda t: t.join(few.select("pair_id"), "pair_id", "left_semi")
    e = some(easy)
    return few, X.informative(some(inc), e).select("pair_id", "feature_id", "x").persist(), e.persist()


def by_id(log):
    return {r.pair_id: r.label for r in log.collect()}


def test_rounds_equal_kernel(small):
    few, inc, easy = small
    s = Settings(labels_per_round=40, k=40, refresh=0.0, interval_cap=20)
    assert by_id(infer.label_rounds(few, inc, easy, s)) == by_id(infer.label_kernel(few, inc, easy, s))


def test_row_order_does_not_matter(small):
    few, inc, easy = small
    s = Settings(labels_per_round=5, fit_above=0.05)
    assert by_id(infer.label_kernel(few, inc, easy, s)) == by_id(infer.label_kernel(few.repartition(7), inc.repartition(5, "x"), easy.repartition(3), s))


def test_scalable_agrees_with_exact(small):
    few, inc, easy = small
    exact = by_id(infer.label_kernel(few, inc, easy, Settings(refresh=0.0, labels_per_round=10), exact=True))
    scalable = by_id(infer.label_kernel(few, inc, easy, Settings(m=None, k=10_000, interval_cap=10_000, refresh=0.0, labels_per_round=10)))
    assert sum(exact[i] == scalable[i] for i in exact) >= 0.95 * len(exact)


def test_one_round_against_a_plain_loop(small):
    few, inc, easy = small
    e = {r.pair_id: r.label for r in easy.collect()}
    entries = inc.toPandas()
    s = Settings(use_mle=False, refresh=0.0, max_rounds=1)
    log = infer.label_kernel(few, inc, easy, s).where("round = 1").collect()
    n1, n0 = sum(e.values()), len(e) - sum(e.values())
    z, sup = {}, {}
    for f, g in entries.groupby("feature_id"):
        known = g[g.pair_id.isin(e)]
        y = known.pair_id.map(e)
        st = [[(y == c).sum() if k == 0 else (known.x[y == c] ** k).sum() for k in (0, 1, 2)] for c in (0, 1)]
        c = I.curves_np(np.array([st[0] + st[1]], dtype=float), n0 / n1, s)
        if not c["active"][0]:
            continue
        for r in g[~g.pair_id.isin(e)].itertuples():
            root = math.sqrt(1 + 1 / c["nobs"][0] + (r.x - c["xbar"][0]) ** 2 / c["dev"][0])
            t = (1 + I.central_t_np(np.array([1 / (c["sigma"][0] * root)]), np.array([c["nobs"][0] - 2]))[0]) / 2
            z[r.pair_id] = z.get(r.pair_id, 0) + t * c["tau"][0] * (r.x - c["alpha"][0])
            sup[r.pair_id] = sup.get(r.pair_id, 0) + math.log(t / (1 - t))
    h = {i: -sum(q * math.log2(q) for q in (1 / (1 + math.exp(-v)), 1 / (1 + math.exp(v))) if 0 < q < 1) for i, v in z.items()}
    best = min(h, key=lambda i: (round(h[i], 9), i))
    assert log[0].pair_id == best and log[0].label == int(z[best] >= 0)


def test_whole_run_against_plain_loops(small):
    """The method as described, once more in plain loops: lines by least squares, confidence by integrating the density, fits by long gradient runs."""
    few, inc, easy = small
    s = Settings(m=30, k=3, interval_cap=8, max_rounds=25)
    log = sorted(infer.label_kernel(few, inc, easy, s).where("round between 1 and 25").collect(), key=lambda r: r.round)
    known = {r.pair_id: r.label for r in easy.collect()}
    has: dict[int, list[tuple[int, float]]] = {r.pair_id: [] for r in few.collect()}
    for r in inc.collect():
        has[r.pair_id].append((r.feature_id, r.x))
    of: dict[int, list[tuple[int, float]]] = {}
    for p, own in has.items():
        for f, x in own:
            of.setdefault(f, []).append((p, x))
    seen: dict[tuple, float] = {}

    def confidence(q, dof):
        if (q, dof) not in seen:
            t = np.linspace(0, q, 801)
            density = np.exp(math.lgamma((dof + 1) / 2) - math.lgamma(dof / 2)) / math.sqrt(dof * math.pi) * (1 + t * t / dof) ** (-(dof + 1) / 2)
            seen[q, dof] = 2 * float(np.trapezoid(density, t))
        return seen[q, dof]

    assert len(log) == 25
    for row in log:
        n1 = sum(known.values())
        w = (len(known) - n1) / n1
        curve = {}
        for f, own in of.items():
            ev = [(x, known[p]) for p, x in own if p in known]
            by = [[x for x, y in ev if y == c] for c in (0, 1)]
            if len(ev) <= 2 or not by[0] or not by[1] or np.mean(by[0]) >= np.mean(by[1]):
                continue
            x, y = np.array([e[0] for e in ev]), np.array([s.label_logit if e[1] else -s.label_logit for e in ev])
            root = np.sqrt([w if e[1] else 1.0 for e in ev])
            dev = ((x - x.mean()) ** 2).sum()
            if dev <= 1e-9:
                continue
            slope, at0 = np.linalg.lstsq(np.column_stack([x, np.ones(len(x))]) * root[:, None], y * root, rcond=None)[0]
            if slope <= 0:
                continue
            sigma = math.sqrt(((y - slope * x - at0) ** 2).sum() / (len(x) - 2))
            curve[f] = (slope, -at0 / slope, sigma, x.mean(), dev, len(x), np.mean(by[0]), np.mean(by[1]))

        def theta(f, x):
            _, _, sigma, mean, dev, n, _, _ = curve[f]
            return (1 + confidence(1 / (sigma * math.sqrt(1 + 1 / n + (x - mean) ** 2 / dev)), n - 2)) / 2

        def entropy(p):
            return round(-sum(q * math.log2(q) for q in (p, 1 - p) if q > 0), 9)

        open_ = [p for p in has if p not in known]
        on = {p: [(f, x) for f, x in has[p] if f in curve] for p in open_}
        support = {p: sum(math.log(theta(f, x) / (1 - theta(f, x))) for f, x in on[p]) for p in open_}
        best = sorted(open_, key=lambda p: (-round(support[p], 9), p))[: s.m]
        approx = {p: 1 / (1 + math.exp(-sum(theta(f, x) * curve[f][0] * (x - curve[f][1]) for f, x in on[p]))) for p in best}
        top = sorted(best, key=lambda p: (entropy(approx[p]), p))[: s.k]
        fitted = {}
        for p in top:
            entries = []
            for c, (f, _) in enumerate(on[p]):
                cells: dict[int, list] = {}
                for q, x in of[f]:
                    if q in known:
                        cells.setdefault(min(9, int(x * 10)), []).append((hashlib.md5(str(q).encode()).hexdigest(), q, x))
                entries += [(q, c, theta(f, x), x) for cell in cells.values() for _, q, x in sorted(cell)[: s.interval_cap]]
            rows = sorted({e[0] for e in entries})
            lo, hi = (np.array([curve[f][k] for f, _ in on[p]]) for k in (6, 7))
            args = [np.array(v) for v in zip(*[(rows.index(q), c, t, x) for q, c, t, x in entries], strict=True)]
            alpha, tau, _ = fit(args[0].astype(int), args[1].astype(int), args[2], args[3], np.array([known[q] for q in rows]), lo, hi, 20.0, w, steps=6000, tol=1e-9)
            fitted[p] = 1 / (1 + math.exp(-sum(theta(f, x) * tau[c] * (x - alpha[c]) for c, (f, x) in enumerate(on[p]))))
        assert row.fits == len(top) and row.pair_id in top
        assert row.p_approx == pytest.approx(approx[row.pair_id], abs=1e-5)
        assert row.support == pytest.approx(1 / (1 + math.exp(-support[row.pair_id])), abs=1e-5)
        assert row.p == pytest.approx(fitted[row.pair_id], abs=2e-3) and row.label == int(fitted[row.pair_id] >= 0.5)
        assert entropy(fitted[row.pair_id]) <= min(entropy(v) for v in fitted.values()) + 5e-3
        known[row.pair_id] = row.label


def test_fits_together_reach_the_least_loss():
    """Several targets at once against each alone by long gradient runs."""
    rng = np.random.default_rng(2)
    for _ in range(5):
        n, lo = 120, rng.uniform(0, 0.4, 4)
        hi = lo + rng.uniform(0.1, 0.5, 4)
        label = (rng.random(n) < 0.3).astype(int)
        x = np.clip(rng.normal(0.3 + 0.4 * label[:, None], 0.2, (n, 4)), 0, 1)
        f = np.tile(np.arange(4), n)
        p = np.repeat(np.arange(n), 4)
        evidence = {k: np.nonzero((f == k) & (rng.random(4 * n) < 0.6))[0] for k in range(4)}
        feats = [np.array([0, 1]), np.array([0, 1, 2]), np.array([0, 3]), np.array([0, 1, 2, 3])]
        got = infer.fit_together(feats, evidence.get, p, f, x.ravel(), label, lo, hi, lambda f, x: 0.6 + 0.1 * f, 20.0, 3.0, [{}] * 4, {}, np.full(n, -1))
        for own, end in zip(feats, got, strict=True):
            e = np.concatenate([evidence[k] for k in own])
            rows, row = np.unique(p[e], return_inverse=True)
            col = np.searchsorted(own, f[e])
            args = (row, col, 0.6 + 0.1 * f[e], x.ravel()[e], label[rows])
            alpha, tau, _ = fit(*args, lo[own], hi[own], 20.0, 3.0, steps=20_000, tol=1e-9)
            v = np.array([end[k] for k in own.tolist()])
            mine = (v[:, 0] * lo[own] + v[:, 1] * hi[own]) / np.maximum(v.sum(1), 1e-12)
            assert loss(*args, mine, v.sum(1), 3.0) <= loss(*args, alpha, tau, 3.0) + 1e-5


def test_supervised_runs(spark, sf, prepared):
    pairs = prepared[0]
    for method in ("svm", "mlp"):
        got = B.supervised_runs(pairs, Q.cluster_truth(spark, sf), method, (0.1, 0.3), 3).toPandas()
        assert len(got) == 6 and (got.f1 > 0.6).all()
        assert got[got.share == 0.3].f1.mean() > got[got.share == 0.1].f1.mean() - 0.02


def test_minimum_hashes_find_similar_titles(spark, sf):
    left, right = Q.left(spark, sf), Q.right(spark, sf)
    met = {(r.id_a, r.id_b) for r in W.block_minhash(left, right).collect()}
    a, b = ({r.rec_id: set(r.title) for r in t.collect()} for t in (left, right))
    near = [(i, j) for i in a for j in b if a[i] and len(a[i] & b[j]) >= 0.7 * len(a[i] | b[j])]
    assert len(near) > 50 and sum(x in met for x in near) >= 0.97 * len(near)


def test_unsupported_pairs(spark):
    pairs = spark.createDataFrame([(1, 0.9), (2, 0.1), (3, 0.2)], "pair_id long, sim double")
    inc = spark.createDataFrame([], "pair_id long, feature_id long, x double")
    easy = spark.createDataFrame([(1, 1), (2, 0)], "pair_id long, label int")
    for how, want in (("match", 1), ("nonmatch", 0), ("similarity", 0)):
        r = infer.label_kernel(pairs, inc, easy, Settings(unsupported=how)).where("pair_id = 3").first()
        assert r.label == want and r.unsupported and r.p == 0.5


def test_resumed_run_labels_the_rest(small):
    few, inc, easy = small
    s = Settings(use_mle=False, refresh=0.0, labels_per_round=3)
    whole = infer.label_kernel(few, inc, easy, s).persist()
    half = infer.resume_labels(whole.where("round <= 10"))
    assert by_id(infer.label_kernel(few, inc, half, s)) == by_id(whole)


def test_similarity_joins_agree(spark, sf):
    s = Q.left(spark, sf).select("rec_id", F.array_distinct("words").alias("s"))
    a, b = (sorted((r.id_a, r.id_b, round(r.sim, 9)) for r in planner.similarity_join(s, s, 0.4, how).collect()) for how in ("loop", "prefix"))
    assert a == b and planner.explain_choice(s, s) == "loop"


def test_components(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 102), (101, 102)], "a long, b long")
    got = {r.node: r.root for r in planner.connected_components(links, "a", "b").collect()}
    assert got == {i: 0 for i in range(41)} | {100: 100, 101: 100, 102: 100}


def test_plans(spark, sf):
    """Pushed filters, pruned columns, no cross join in blocking."""
    li = spark.read.parquet(f"{sf}/lineitem.parquet").where("l_quantity > 40").select("l_orderkey")
    text = li._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,40" in text and "ReadSchema: struct<l_orderkey:bigint,l_quantity:" in text
    blocking = W.block_by_tokens(Q.left(spark, sf), Q.right(spark, sf))._jdf.queryExecution().toString()
    assert "CartesianProduct" not in blocking and "BroadcastNestedLoopJoin" not in blocking
    with pytest.raises(ValueError):
        W.pairs_all(Q.left(spark, sf), Q.right(spark, sf), 10)


def test_support_product_form(spark):
    """The sum of log-odds equals the products' ratio."""
    rows = pd.DataFrame({"pair_id": [1, 1, 1], "theta": [0.7, 0.6, 0.9]})
    got = G.support(spark.createDataFrame(rows)).first()["support"]
    a, b = np.prod(rows.theta), np.prod(1 - rows.theta)
    assert got == pytest.approx(a / (a + b))
    assert replace(Settings(), k=3).k == 3


def test_containment_whole_texts_and_common_tokens(spark):
    """A passage in over 200 documents, one of over 64 tokens, one deep in a document, repeated tokens, odd rows."""
    from pairlabel.operators.containment import contained

    long = [f"w{k}" for k in range(90)]
    passages = [(1, "one two three four five"), (2, " ".join(long)), (3, "a a b a a b c"), (4, None), (5, "..."), (6, "never met")]
    docs = [(k, f"x{k} One, two three four five y{k}") for k in range(300)]
    docs += [(1000, "z " * 5000 + " ".join(long)), (1001, "b a a b a"), (1002, None), (None, "c"), (1003, "a b"), (1003, "b a")]

    def run(a, b):
        return max((n for i in range(len(a)) for j in range(len(b)) for n in range(1, len(a) - i + 1) if a[i : i + n] == b[j : j + n]), default=0)

    want = [(1, k, 1.0, 5) for k in range(300)] + [(2, 1000, 1.0, 90)]
    words = "a a b a a b c".split()
    want += [(3, k, round(len(set(words) & set(t.split())) / 3, 6), run(words, t.split())) for k, t in docs[301:] if t]
    a, b = spark.createDataFrame(passages, "item_id long, text string"), spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    for block_tokens in (100_000, 6):
        assert sorted(map(str, contained(a, b, block_tokens).collect())) == sorted(f"Row(item_id={i}, doc_id={k}, contained={c}, run={n})" for i, k, c, n in want)
    assert contained(a.limit(0), b).count() == contained(a, b.limit(0)).count() == 0


def test_residuals_are_summed_in_one_chain(spark):
    """On a line without residuals sigma is rounding alone, so the order of its six terms decides it."""
    rng = np.random.default_rng(5)
    rows = []
    for k in range(400):
        a, b, n0, n1 = rng.random(), rng.random(), int(rng.integers(1, 9)), int(rng.integers(1, 9))
        rows.append((k, n0, n0 * a, n0 * a * a, n1, n1 * b, n1 * b * b))
    stats = spark.createDataFrame(rows, "feature_id long, n0 long, s0 double, q0 double, n1 long, s1 double, q1 double")
    got = {r.feature_id: r.sigma for r in G.fit_curves(stats, spark.createDataFrame([(1.7,)], "w double"), Settings()).collect()}
    z, w = Settings().label_logit, 1.7
    for k, n0, s0, q0, n1, s1, q1 in rows:
        sw, sx, sxx, sy, sxy = n0 + w * n1, s0 + w * s1, q0 + w * q1, (w * n1 - n0) * z, (w * s1 - s0) * z
        if sw * sxx - sx * sx > 1e-9 and n0 + n1 > 2:
            tau = (sw * sxy - sx * sy) / (sw * sxx - sx * sx)
            icpt = (sy - tau * sx) / sw
            lo, hi = -z - icpt, z - icpt
            rss = n0 * lo * lo - 2 * tau * lo * s0 + tau * tau * q0 + n1 * hi * hi - 2 * tau * hi * s1 + tau * tau * q1
            assert got[k] == math.sqrt(max(rss / (n0 + n1 - 2), 0.0))


@pytest.mark.parametrize("method", ["svm", "mlp"])
def test_supervised_runs_do_not_repeat_the_data(spark, method):
    """All runs learn from what one broadcast holds: no shuffle with a copy of the rows for each run."""
    rows = [(i, *[(i * k % 17) / 16 for k in (1, 3, 5, 7)], [f"t{i % 9}", f"u{i % 4}"], [f"t{i % 9}", f"u{i % 3}"]) for i in range(400)]
    pairs = spark.createDataFrame(rows, "pair_id long, sim_title double, sim_body double, sim_source double, sim_num double, title_a array<string>, title_b array<string>")
    truth = pairs.select("pair_id", (F.col("sim_title") > 0.5).cast("int").alias("truth"))
    runs = B.supervised_runs(pairs, truth, method, shares=(0.3,), runs=2)
    assert "Exchange" not in runs._jdf.queryExecution().executedPlan().toString()
    got = {r.run: r for r in runs.collect()}
    assert set(got) == {0, 1} and all(r.f1 > 0.8 and r.method == method for r in got.values())
    assert B.supervised_runs(pairs.limit(0), truth, method, runs=1).count() == 0


@pytest.mark.parametrize("exact", [False, True])
def test_kernel_labels_workloads_of_any_size(spark, exact):
    """Over 200,000 pairs, or 50,000 in the exact mode, it refused before."""
    n = 50_100 if exact else 200_100
    pairs = spark.range(n).select(F.col("id").alias("pair_id"), (F.col("id") % 101 / 100).alias("sim"))
    known = "pair_id % 1000 <> 7"
    inc = pairs.where(f"pair_id < 900 or not ({known})").select("pair_id", F.lit((1 << 59) + 1).alias("feature_id"), F.col("sim").alias("x"))
    easy = pairs.where(known).select("pair_id", (F.col("sim") >= 0.5).cast("int").alias("label"))
    log = infer.label_kernel(pairs, inc, easy, Settings(labels_per_round=100, k=100), exact=exact).persist()
    open_ = log.where("not easy")
    assert log.select("pair_id").distinct().count() == log.count() == n
    assert open_.count() == pairs.where(f"not ({known})").count() and open_.where("fits < 0 or label not in (0, 1)").count() == 0
    assert {r.label for r in open_.select("label").distinct().collect()} == {0, 1}


def test_whole_areas_are_made_once_for_a_feature(spark):
    """Before, each entry integrated twice, once for what normalises it; the numbers are the same to the last bit."""
    inc = spark.createDataFrame([(p, f, (7 * p + f) % 11 / 11) for p in range(40) for f in range(3)], "pair_id long, feature_id long, x double")
    labels = inc.where("feature_id = 1 and pair_id < 30").select("pair_id", (F.col("x") > 0.5).cast("int").alias("label"))
    curves = G.fit_curves(G.feature_stats(inc, labels), G.class_weight(labels), Settings()).persist()
    out = G.with_confidence(inc, curves, Settings())
    assert out._jdf.queryExecution().optimizedPlan().expressions().mkString().count("aggregate(") == 1
    twice = inc.join(curves.where("active"), "feature_id").select("pair_id", "feature_id", I.normalize(I.confidence(Settings(), F.col("x"))).alias("was"))
    both = out.join(twice, ["pair_id", "feature_id"])
    assert both.count() == out.count() > 0 and both.where("theta <> was").count() == 0


@pytest.mark.parametrize("method", ["svm", "mlp"])
def test_supervised_runs_take_any_number_of_pairs(spark, method):
    """Over 500,000 pairs they refused before; a few run to keep this short."""
    n, at = 500_100, F.col("id")
    pairs = spark.range(n).select(at.alias("pair_id"), *[(at * k % 17 / 16).alias(c) for k, c in zip((1, 3, 5, 7), W.PARTS, strict=True)], *[F.array(F.concat(F.lit("t"), (at % k).cast("string"))).alias(c) for k, c in ((9, "title_a"), (4, "title_b"))])
    truth = pairs.select("pair_id", (F.col("sim_title") > 0.5).cast("int").alias("truth"))
    got = B.supervised_runs(pairs, truth, method, shares=(0.06,), runs=1).collect()
    assert [(r.method, r.share, r.run) for r in got] == [(method, 0.06, 0)] and got[0].f1 > 0.9


def test_newton_steps_over_parts_are_those_over_all_rows(spark):
    """Classifiers from sums over partitions against plain Newton steps over one array; one share has no training rows, one truth a single class."""
    rng = np.random.default_rng(3)
    x = rng.uniform(size=(900, 4)).round(3)
    y = (x @ [1, 1, 0.5, -1] + rng.normal(0, 0.2, 900) > 0.8).astype(int)
    rows = [(i, *x[i].tolist(), int(y[i])) for i in range(900)]
    table = spark.createDataFrame(rows, "pair_id long, a double, b double, c double, d double, truth int").repartition(7)
    data = table.select("pair_id", F.array("a", "b", "c", "d").alias("x"), "truth")
    drawn = {r.pair_id: r.drawn for r in B.with_draws(data, 2).collect()}
    models = B.train_svms(data, [(0.3, 0), (0.3, 1), (0.0, 0)])
    assert models[2] == ("same", 0) and B.train_svms(data.withColumn("truth", F.lit(1)), [(0.3, 0)]) == [("same", 1)]
    for r in (0, 1):
        own = np.array([drawn[i][r] / 1e6 < 0.3 for i in range(900)])
        mean, scale, z = x[own].mean(0), x[own].std(0) + 1e-9, (x - x[own].mean(0)) / (x[own].std(0) + 1e-9)
        a = np.column_stack([z, *[z[:, i] * z[:, j] for i in range(4) for j in range(i, 4)], np.ones(900)])
        s, weight, w = 2.0 * y[own] - 1, np.where(y[own], 0.5 / y[own].sum(), 0.5 / (1 - y[own]).sum()), np.zeros(15)
        for _ in range(25):
            gap = 1 - s * (a[own] @ w)
            on = gap > 0
            t = a[own][on]
            w = w - np.linalg.solve((t * weight[on][:, None]).T @ t + 1e-3 * np.eye(15), 1e-3 * w - t.T @ (weight[on] * s[on] * gap[on]))
        assert np.allclose(models[r][1], mean) and np.allclose(models[r][2], scale) and np.allclose(models[r][3], w, atol=1e-8)
        assert (B.predict(models[r], x) == (a @ w >= 0)).all()
