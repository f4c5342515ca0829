"""Staged labeling: easy pairs first, then round by round the pair that is most certain.

Two executors give the same labels. ``label_kernel`` runs the rounds of a whole
workload, or of each shard of one, inside one ``applyInPandas`` group, so a
sequential round costs no Spark job; its state is a few numbers per feature and pair.
``label_rounds`` runs each round as Spark jobs over tables of any size and is meant
for many labels per round.
"""

from __future__ import annotations

import hashlib
import heapq

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import influence as I
from ..settings import Settings
from . import graph
from .fit import Own, fit, fit_many

LOG = "pair_id long, label int, round int, support double, p_approx double, p double, h double, flipped boolean, unsupported boolean, easy boolean, fits int"
#: In place of a label of 0 or 1: of a pair without one, and of a row that is a feature's entry.
UNKNOWN, ENTRY = -1, -2


def _cap_order(ids: np.ndarray) -> np.ndarray:
    """The same numbers as workload.hash_order."""
    return np.array([int(hashlib.md5(str(i).encode()).hexdigest()[:15], 16) for i in ids.tolist()], dtype=np.int64)


def fit_together(feats, evidence, p, f, x, label, lo, hi, theta_at, tau_max, weight, known, near, place) -> list[dict[int, tuple[float, float]]]:
    """Fits of several targets, each on its own capped subgraph; what these share, which is most, is laid out once. Per target: p and q of each of its features.

    feats: features of each target; evidence: of a feature the numbers of its capped entries, whose pair, feature and value are p, f, x; label: of pairs;
    known, near: where the fits of this target, and of any target, ended last; place: room of a number per pair, all -1, which is left so.
    """
    each, held = np.unique(np.concatenate(feats), return_counts=True)
    common = each[held == len(feats)]
    apart = [own[held[np.searchsorted(each, own)] < len(feats)] for own in feats]
    d = len(common)
    parts = [evidence(k) for k in common.tolist()]
    entries = np.concatenate([*parts, np.zeros(0, np.int64)])
    column = np.repeat(np.arange(d), [len(e) for e in parts])
    place[p[entries]] = 0
    rows = np.nonzero(place == 0)[0]
    place[rows] = np.arange(len(rows))
    further = [[evidence(k) for k in own.tolist()] for own in apart]
    loose = np.concatenate([*(e for es in further for e in es), np.zeros(0, np.int64)])
    met = p[loose]
    met = met[place[met] < 0]
    place[met] = len(place)  # a mark beyond all places
    more = np.nonzero(place == len(place))[0]
    place[more] = len(rows) + np.arange(len(more))
    pairs, both = np.concatenate([rows, more]), np.concatenate([entries, loose])
    of, at_x = f[both], x[both]
    theta = theta_at(of, at_x)
    a, b = theta * (at_x - lo[of]), theta * (at_x - hi[of])
    shared = np.zeros((len(pairs), 2 * d))
    where = place[p[entries]]
    shared[where, column], shared[where, d + column] = a[: len(entries)], b[: len(entries)]
    owns, at = [], len(entries)
    for es in further:
        size = [len(e) for e in es]
        span = slice(at, at + sum(size))
        at = span.stop
        own_rows, back = np.unique(place[p[both[span]]], return_inverse=True)
        col = np.repeat(np.arange(len(es)), size)
        columns = np.zeros((len(own_rows), 2 * len(es)))
        columns[back, col], columns[back, len(es) + col] = a[span], b[span]
        owns.append(Own(own_rows, columns))
    place[pairs] = -1
    layout = [[*common.tolist(), *own.tolist()] for own in apart]
    start = np.zeros((len(layout), 2, max(map(len, layout))))
    for r, (own, was) in enumerate(zip(layout, known, strict=True)):
        start[r, :, : len(own)] = np.array([was.get(k) or near.get(k) or (0.5, 0.5) for k in own]).T
    v, _ = fit_many(shared, len(rows), label[pairs], owns, tau_max, weight, start)
    return [dict(zip(own, v[r, :, : len(own)].T.tolist(), strict=True)) for r, own in enumerate(layout)]


class Kernel:
    """State of one workload: pairs, incidence in both directions, statistics, capped evidence, and what each entry adds to its pair."""

    def __init__(self, pair_ids: np.ndarray, sim: np.ndarray, entries: pd.DataFrame, settings: Settings):
        self.s = settings
        order = np.argsort(pair_ids)
        self.ids, self.sim = pair_ids[order], sim[order]
        n = len(self.ids)
        self.names, self.f = np.unique(entries["feature_id"].to_numpy(), return_inverse=True)
        self.p = np.searchsorted(self.ids, entries["pair_id"].to_numpy())
        self.x = entries["x"].to_numpy(dtype=float)
        o = np.lexsort((self.f, self.p))
        self.p, self.f, self.x = self.p[o], self.f[o], self.x[o]
        self.starts = np.searchsorted(self.p, np.arange(n + 1))
        self.by_f = np.argsort(self.f, kind="stable")
        self.f_starts = np.searchsorted(self.f[self.by_f], np.arange(len(self.names) + 1))
        self.cell = self.f * settings.bins + np.clip(np.floor(self.x * settings.bins), 0, settings.bins - 1).astype(int)
        self.order = _cap_order(self.ids)
        self.cells: dict[int, list[tuple[int, int, int]]] = {}  # the first entries of a feature's interval in the order of the cap, the last of them on top
        self.gathered: dict[int, np.ndarray] = {}
        self.label = np.full(n, -1)
        self.stats = np.zeros((len(self.names), 6))
        self.open = np.arange(len(self.x))  # entries of unlabeled pairs, now and then with some of labeled ones
        self.live: tuple | None = None  # those of active features, with their feature, value and pair
        self.theta = np.zeros(len(self.x))
        self.on = np.zeros(len(self.x), dtype=bool)
        self.logit = np.zeros(len(self.x))
        self.force = np.zeros(len(self.x))
        self.support = np.zeros(n)
        self.z = np.zeros(n)
        self.count = np.zeros(n)
        self.since = np.zeros(len(self.names))
        self.curves: dict[str, np.ndarray] = {}
        self.central = I.CentralT()
        self.version = np.zeros(len(self.names), dtype=np.int64)
        self.fits = 0
        self.known: dict[int, tuple[int, float]] = {}
        self.last: dict[int, dict[int, tuple[float, float]]] = {}  # where a target's last fit ended
        self.near: dict[int, tuple[float, float]] = {}  # where any target's last fit ended, by feature
        self.place = np.full(n, -1)

    def weight(self) -> float:
        n1, n0 = int((self.label == 1).sum()), int((self.label == 0).sum())
        return n0 / n1 if n1 and self.s.class_weight else 1.0

    def add(self, pairs: np.ndarray, labels: np.ndarray) -> None:
        self.label[pairs] = labels
        for p, y in zip(pairs.tolist(), labels.tolist(), strict=True):
            e = slice(self.starts[p], self.starts[p + 1])
            f, x = self.f[e], self.x[e]
            at = 3 * y
            self.stats[f, at] += 1  # a pair has a feature once
            self.stats[f, at + 1] += x
            self.stats[f, at + 2] += x * x
            self.since[f] += 1
            rank = (-int(self.order[p]), -p)
            for k, c, own in zip(range(e.start, e.stop), self.cell[e].tolist(), f.tolist(), strict=True):
                cell = self.cells.setdefault(c, [])
                if len(cell) < self.s.interval_cap:
                    heapq.heappush(cell, (*rank, k))
                elif heapq.heappushpop(cell, (*rank, k))[2] == k:
                    continue
                self.gathered.pop(own, None)
            self.last.pop(p, None)
            self.known.pop(p, None)

    def evidence(self, f: int) -> np.ndarray:
        """The feature's entries of labeled pairs, at most the cap in each interval."""
        if f not in self.gathered:
            bins = self.s.bins
            self.gathered[f] = np.array([k for c in range(f * bins, (f + 1) * bins) for _, _, k in self.cells.get(c, ())], dtype=np.int64)
        return self.gathered[f]

    def refresh(self, all_: bool = False) -> None:
        """New curves, and new confidences of the entries of unlabeled pairs; with a setting of refresh, only of features with enough new evidence."""
        w = self.weight()
        every = all_ or self.s.refresh == 0 or abs(w - getattr(self, "w", np.inf)) > self.s.refresh * w
        if every:
            stale = np.arange(len(self.names))
            self.w = w
        else:
            stale = np.nonzero(self.since > self.s.refresh * (self.stats[:, 0] + self.stats[:, 3]))[0]
        if not len(stale):
            return
        own = I.curves_np(self.stats[stale], self.w, self.s)
        if not self.curves:
            self.curves = {k: np.zeros(len(self.names), dtype=v.dtype) for k, v in own.items()}
        for k, v in own.items():
            self.curves[k][stale] = v
        self.since[stale] = 0
        self.version[stale] += 1
        self.lines = I.confidence_lines(self.curves, self.s, self.central)
        if every:
            self._refresh_all()
            return
        e = np.concatenate([self.by_f[self.f_starts[f] : self.f_starts[f + 1]] for f in stale.tolist()])
        e = e[self.label[self.p[e]] < 0]  # only unlabeled pairs need them
        self.live = None
        on = self.curves["active"][self.f[e]]
        f, x = self.f[e], self.x[e]
        theta = self.theta_at(f, x)
        with np.errstate(all="ignore"):
            t = np.minimum(theta, 1 - 1e-12)
            logit = np.where(on, np.log(t / (1 - t)), 0.0)
            force = np.where(on, theta * self.curves["tau"][f] * (x - self.curves["alpha"][f]), 0.0)
        p, n = self.p[e], len(self.ids)
        self.support += np.bincount(p, logit - self.logit[e], n)
        self.z += np.bincount(p, force - self.force[e], n)
        self.count += np.bincount(p, on.astype(float) - self.on[e], n)
        self.theta[e], self.on[e], self.logit[e], self.force[e] = theta, on, logit, force

    def _refresh_all(self) -> None:
        """Support and approximation of all unlabeled pairs anew; what does not depend on the curves is kept between rounds."""
        active, n = self.curves["active"], len(self.ids)
        if self.live is None or not np.array_equal(active, self.live[0]) or (self.label[self.live[4]] < 0).sum() < 0.97 * len(self.live[4]):
            self.open = self.open[self.label[self.p[self.open]] < 0]
            on = active[self.f[self.open]]
            self.on[self.open] = on
            e = self.open[on]
            self.count = np.bincount(self.p[e], minlength=n).astype(float)
            self.live = (active.copy(), e, self.f[e], self.x[e], self.p[e])
        _, e, f, x, p = self.live
        theta = self.theta_at(f, x)
        t = np.minimum(theta, 1 - 1e-12)
        logit, force = np.log(t / (1 - t)), theta * self.curves["tau"][f] * (x - self.curves["alpha"][f])
        self.support, self.z = np.bincount(p, logit, n), np.bincount(p, force, n)
        self.theta[e] = theta
        if self.s.refresh:
            self.logit[:], self.force[:] = 0.0, 0.0
            self.logit[e], self.force[e] = logit, force

    def theta_at(self, f: np.ndarray, x: np.ndarray) -> np.ndarray:
        t = self.central.along(self.lines, f, x)
        return (1 + t) / 2 if self.s.confidence_scale == "normalized" else t

    def infer(self, targets: list[int]) -> np.ndarray:
        """Probabilities of pairs, each by a fit on its own capped subgraph. What the subgraphs share, which is most, is laid out once."""
        out = np.full(len(targets), 0.5)
        mine = {}
        for j, t in enumerate(targets):
            e = np.arange(self.starts[t], self.starts[t + 1])
            e = e[self.on[e]]
            if not len(e):
                continue
            stamp = hash(tuple(self.version[self.f[e]].tolist()))
            if self.known.get(t, (None,))[0] == stamp:
                out[j] = self.known[t][1]
                continue
            mine[j] = e
            self.known[t] = (stamp, 0.5)
        if not mine:
            return out
        feats = [self.f[e] for e in mine.values()]
        known = [self.last.get(targets[j], {}) for j in mine]
        lo, hi = self.curves["lo"], self.curves["hi"]
        ended = fit_together(feats, self.evidence, self.p, self.f, self.x, self.label, lo, hi, self.theta_at, self.s.tau_max, self.w, known, self.near, self.place)
        self.fits += len(feats)
        for (j, e), k, end in zip(mine.items(), feats, ended, strict=True):
            self.last[targets[j]] = end
            self.near.update(end)
            p, q = np.array([end[f] for f in k.tolist()]).T
            z = float((self.theta[e] * (p * (self.x[e] - lo[k]) + q * (self.x[e] - hi[k]))).sum())
            out[j] = 1 / (1 + np.exp(-np.clip(z, -700, 700)))
            self.known[targets[j]] = (self.known[targets[j]][0], out[j])
        return out

    def begin(self, easy: dict[int, int]) -> list[tuple]:
        at = np.searchsorted(self.ids, np.array(sorted(easy), dtype=np.int64))
        self.add(at, np.array([easy[i] for i in sorted(easy)], dtype=int))
        return [(int(self.ids[p]), int(self.label[p]), 0, None, None, float(self.label[p]), 0.0, False, False, True, 0) for p in at.tolist()]

    def run(self, easy: dict[int, int]) -> list[tuple]:
        s, log = self.s, self.begin(easy)
        self.refresh(all_=True)
        rounds = 0
        while True:
            left = np.nonzero(self.label < 0)[0]
            if not len(left) or (s.max_rounds is not None and rounds >= s.max_rounds):
                break
            rounds += 1
            score = np.round(self.support[left] / np.maximum(self.count[left], 1) if s.support_mode == "mean_logit" else self.support[left], 9)
            if s.m is not None and len(left) > s.m:
                cut = np.partition(-score, s.m - 1)[s.m - 1]
                sure, tie = left[-score < cut], left[-score == cut]
                left = np.concatenate([sure, tie[: s.m - len(sure)]])  # ids ascend, so ties go to the smaller
            p = 1 / (1 + np.exp(-np.clip(self.z[left], -700, 700)))
            h = np.round(I.entropy_np(p), 9)
            most = max(s.k, s.labels_per_round)
            near = np.nonzero(h <= np.partition(h, most - 1)[most - 1])[0] if len(h) > most else np.arange(len(h))
            top = near[np.lexsort((left[near], h[near]))[:most]]
            cand, p_a = left[top], p[top]
            p_m, before = p_a.copy(), self.fits
            fit_it = np.nonzero(s.use_mle & (h[top] >= s.fit_above))[0]
            if len(fit_it):
                p_m[fit_it] = self.infer(cand[fit_it].tolist())
            h_m = np.round(I.entropy_np(p_m), 9)
            first = np.lexsort((cand, h_m))
            chosen = [j for r, j in enumerate(first[: s.labels_per_round].tolist()) if r == 0 or s.h_max is None or h_m[j] <= s.h_max]
            labels = []
            for j in chosen:
                c = cand[j]
                alone = self.count[c] == 0
                y = int(p_m[j] >= s.threshold)
                if alone and s.unsupported != "match":
                    y = 0 if s.unsupported == "nonmatch" else int(self.sim[c] >= s.threshold)
                labels.append(y)
                sup = 1 / (1 + np.exp(-np.clip(self.support[c], -700, 700)))
                fits = self.fits - before if j == chosen[0] else 0
                log.append((int(self.ids[c]), y, rounds, float(sup), float(p_a[j]), float(p_m[j]), float(h_m[j]), bool((p_a[j] >= s.threshold) != (p_m[j] >= s.threshold)), bool(alone), False, fits))
            self.add(cand[chosen], np.array(labels, dtype=int))
            self.refresh()
        for c in np.nonzero(self.label < 0)[0].tolist():  # what a limit of rounds has left is decided by the approximation
            p = float(1 / (1 + np.exp(-np.clip(self.z[c], -700, 700))))
            log.append((int(self.ids[c]), int(p >= s.threshold), rounds + 1, None, p, p, float(I.entropy_np(np.array([p]))[0]), False, bool(self.count[c] == 0), False, 0))
        return log


def label_exact_np(kernel: Kernel, easy: dict[int, int], batch: int = 1) -> list[tuple]:
    """The exact mode: one joint fit on all evidence per round, every unlabeled pair scored, the surest labeled. A fit starts where the last one ended."""
    s, k = kernel.s, kernel
    log = k.begin(easy)
    rounds = 0
    ended = np.full((2, len(k.names)), 0.5)
    while (k.label < 0).any():
        k.refresh(all_=True)
        rounds += 1
        on = np.nonzero(k.curves["active"][k.f])[0]
        ev = on[k.label[k.p[on]] >= 0]
        feats, col = np.unique(k.f[ev], return_inverse=True)
        pairs, row = np.unique(k.p[ev], return_inverse=True)
        alpha, tau = np.zeros(len(k.names)), np.zeros(len(k.names))
        if len(ev):
            lo, hi = k.curves["lo"][feats], k.curves["hi"][feats]
            a, t, _ = fit(row, col, k.theta_at(k.f[ev], k.x[ev]), k.x[ev], k.label[pairs], lo, hi, s.tau_max, k.w, start=ended[:, feats].ravel())
            alpha[feats], tau[feats] = a, t
            ended[0, feats], ended[1, feats] = t * (hi - a) / (hi - lo), t * (a - lo) / (hi - lo)
        open_ = on[k.label[k.p[on]] < 0]
        z = np.bincount(k.p[open_], k.theta[open_] * tau[k.f[open_]] * (k.x[open_] - alpha[k.f[open_]]), minlength=len(k.ids))
        left = np.nonzero(k.label < 0)[0]
        p = 1 / (1 + np.exp(-np.clip(z[left], -700, 700)))
        h = np.round(I.entropy_np(p), 9)
        for r, j in enumerate(np.lexsort((left, h))[:batch].tolist()):
            y = int(p[j] >= s.threshold)
            log.append((int(k.ids[left[j]]), y, rounds, None, None, float(p[j]), float(h[j]), False, bool(k.count[left[j]] == 0), False, int(r == 0 and len(ev) > 0)))
            k.add(left[[j]], np.array([y]))
    return log


def _one_table(pairs: DataFrame, incidence: DataFrame, easy: DataFrame, shard: str | None) -> DataFrame:
    """Pairs, entries and easy labels as rows of one table with a shard number. No column of numbers has nulls, so a task gets arrays and not objects: the label of a pair is 0, 1 or UNKNOWN, that of an entry is ENTRY."""
    own = F.col(shard).cast("long") if shard else F.lit(0).cast("long")
    shards = pairs.select("pair_id", own.alias("shard"), "sim")
    e = easy.select("pair_id", F.col("label").alias("label"))
    base = shards.join(e, "pair_id", "left").select("shard", "pair_id", F.lit(0).cast("long").alias("feature_id"), F.col("sim").alias("x"), F.coalesce(F.col("label").cast("int"), F.lit(UNKNOWN)).alias("label"))
    inc = incidence.select("pair_id", "feature_id", "x").join(shards.select("pair_id", "shard"), "pair_id")
    return base.unionByName(inc.select("shard", "pair_id", "feature_id", "x", F.lit(ENTRY).alias("label")))


def label_kernel(pairs: DataFrame, incidence: DataFrame, easy: DataFrame, settings: Settings = Settings(), shard: str | None = None, exact: bool = False) -> DataFrame:
    """The round log, one row per pair: see LOG. shard: a column of pairs; each shard is a workload of its own and a task's memory, whatever its size; label_rounds has no such bound."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        base = rows["label"].to_numpy() != ENTRY
        own, entries = rows[base], rows[~base]
        k = Kernel(own["pair_id"].to_numpy(), own["x"].to_numpy(dtype=float), entries, settings)
        known = own[own["label"] != UNKNOWN]
        easy_ = dict(zip(known["pair_id"].tolist(), known["label"].tolist(), strict=True))
        log = label_exact_np(k, easy_, settings.labels_per_round) if exact else k.run(easy_)
        out = pd.DataFrame(log, columns=[c.split()[0] for c in LOG.split(", ")])
        for c in ("support", "p_approx", "p", "h"):
            out[c] = out[c].astype(float)
        return out

    return _one_table(pairs, incidence, easy, shard).groupBy("shard").applyInPandas(run, LOG)


def fit_targets(asked: DataFrame, evidence: DataFrame, curves: DataFrame, weight: float, settings: Settings, batch: int = 16, n_targets: int | None = None) -> DataFrame:
    """target, p: each target fitted on its capped subgraph. Targets go in batches of about ``batch``; a batch's evidence is sent once, though its targets share most of it.

    asked: target, feature_id, target_x; evidence: feature_id, pair_id, x, label, capped. A batch's memory is bounded by the cap and the features of its targets.
    """
    from ..plans.planner import cut

    asked = asked.join(curves.where("active"), "feature_id")
    n = n_targets if n_targets is not None else asked.select("target").distinct().count()
    batches = max(1, -(-n // batch))
    asked = cut(asked.withColumn("batch", F.pmod(F.xxhash64("target"), F.lit(batches)).cast("int")), "asked")
    needed = asked.select(F.col("batch").alias("part"), F.col("feature_id").alias("_f")).distinct()
    sent = evidence.select("feature_id", "pair_id", "x", "label").join(needed, F.col("feature_id") == F.col("_f")).drop("_f")

    def run(own: pd.DataFrame, rows: pd.DataFrame) -> pd.DataFrame:
        if own.empty:
            return pd.DataFrame({"target": [], "p": []})
        names, own_f = np.unique(own["feature_id"].to_numpy(), return_inverse=True)
        first = own.drop_duplicates("feature_id").set_index("feature_id").loc[names]
        curve = {c: first[c].to_numpy() for c in ("tau", "alpha", "sigma", "xbar", "dev", "nobs", "active", "lo", "hi")}
        scale = (lambda t: (1 + t) / 2) if settings.confidence_scale == "normalized" else (lambda t: t)
        theta_at = lambda f, x: scale(I.confidence_np(curve, f, x, settings))
        rows = rows.sort_values(["feature_id", "pair_id"])
        f, x = np.searchsorted(names, rows["feature_id"].to_numpy()), rows["x"].to_numpy(dtype=float)
        pairs, p = np.unique(rows["pair_id"].to_numpy(), return_inverse=True)
        label = np.zeros(len(pairs), dtype=int)
        label[p] = rows["label"].to_numpy()
        spans = np.searchsorted(f, np.arange(len(names) + 1))
        targets, at = np.unique(own["target"].to_numpy(), return_inverse=True)
        order = np.lexsort((own_f, at))
        cuts = np.searchsorted(at[order], np.arange(len(targets) + 1))
        mine = [order[s:e] for s, e in zip(cuts, cuts[1:], strict=False)]
        feats = [own_f[m] for m in mine]
        ended = fit_together(feats, lambda k: np.arange(spans[k], spans[k + 1]), p, f, x, label, curve["lo"], curve["hi"], theta_at, settings.tau_max, weight, [{}] * len(feats), {}, np.full(len(pairs), -1))
        out, tx = [], own["target_x"].to_numpy(dtype=float)
        for m, k, end in zip(mine, feats, ended, strict=True):
            v = np.array([end[c] for c in k.tolist()])
            z = float((theta_at(k, tx[m]) * (v[:, 0] * (tx[m] - curve["lo"][k]) + v[:, 1] * (tx[m] - curve["hi"][k]))).sum())
            out.append(1 / (1 + np.exp(-np.clip(z, -700, 700))))
        return pd.DataFrame({"target": targets, "p": out})

    return asked.groupBy("batch").cogroup(sent.groupBy("part")).applyInPandas(run, "target long, p double")


def label_rounds(pairs: DataFrame, incidence: DataFrame, easy: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """Each round as Spark jobs. Labels are append-only tables in the shared folder, from which an interrupted run can go on."""
    from ..plans.planner import cut

    s = settings
    incidence = cut(incidence.select("pair_id", "feature_id", "x").repartition("feature_id"), "incidence")
    pairs = cut(pairs.select("pair_id", "sim"), "pairs")
    one = F.lit(None).cast("double")
    log = cut(
        easy.select("pair_id", F.col("label").cast("int").alias("label"), F.lit(0).alias("round"), one.alias("support"), one.alias("p_approx"), F.col("label").cast("double").alias("p"), F.lit(0.0).alias("h"), F.lit(False).alias("flipped"), F.lit(False).alias("unsupported"), F.lit(True).alias("easy"), F.lit(0).alias("fits")),
        "round-0",
    )
    rounds = 0
    stats = cut(graph.feature_stats(incidence, log), "stats")
    while True:
        labels = log.select("pair_id", "label")
        left = pairs.join(labels, "pair_id", "left_anti")
        if (s.max_rounds is not None and rounds >= s.max_rounds) or not left.limit(1).count():
            break
        rounds += 1
        weight = cut(graph.class_weight(labels), "weight")
        w = weight.first()["w"] if s.class_weight else 1.0
        curves = cut(graph.fit_curves(stats, weight, s), "curves")
        entries = graph.with_confidence(incidence.join(left.select("pair_id"), "pair_id", "left_semi"), curves, s)
        sup = left.select("pair_id").join(graph.support(entries, s), "pair_id", "left").select("pair_id", F.coalesce("log_odds", F.lit(0.0)).alias("log_odds"), F.coalesce("features", F.lit(0)).alias("features"))
        cand = cut(graph.top_support(sup, s.m), "by-support")
        approx = graph.approx_probability(entries.join(F.broadcast(cand.select("pair_id")) if s.m else cand.select("pair_id"), "pair_id", "left_semi"))
        approx = cand.join(approx, "pair_id", "left").select("pair_id", "log_odds", "features", F.coalesce("p", F.lit(0.5)).alias("p_approx"), F.coalesce("h", F.lit(1.0)).alias("h"))
        top = cut(graph.top_certain(approx, max(s.k, s.labels_per_round)), "by-certainty")
        if s.use_mle:
            asked = top.where(F.round("h", 9) >= s.fit_above)
            fits = asked.where("features > 0").count()
            own = graph.own_features(incidence, asked)
            p = fit_targets(own, graph.capped(graph.evidence_of(incidence, labels, asked), s.interval_cap, 8), curves, w, s, n_targets=max(s.k, s.labels_per_round))
            top = top.join(p, top["pair_id"] == p["target"], "left").withColumn("p", F.coalesce("p", "p_approx"))
        else:
            top, fits = top.withColumn("p", F.col("p_approx")), 0
        top = top.withColumn("h", I.entropy(F.col("p"))).orderBy(F.round("h", 9), "pair_id").limit(s.labels_per_round)
        if s.h_max is not None and s.labels_per_round > 1:
            best = top.agg(F.min(F.struct(F.round("h", 9), "pair_id"))["pair_id"].alias("best"))
            top = top.join(F.broadcast(best)).where((F.col("h") <= s.h_max) | (F.col("pair_id") == F.col("best")))
        y = (F.col("p") >= s.threshold).cast("int")
        if s.unsupported == "nonmatch":
            y = F.when(F.col("features") == 0, 0).otherwise(y)
        elif s.unsupported == "similarity":
            top = top.join(pairs, "pair_id")
            y = F.when(F.col("features") == 0, (F.col("sim") >= s.threshold).cast("int")).otherwise(y)
        new = top.select(
            "pair_id", y.alias("label"), F.lit(rounds).alias("round"), I.logistic(F.col("log_odds")).alias("support"), "p_approx", "p", "h",
            ((F.col("p") >= s.threshold) != (F.col("p_approx") >= s.threshold)).alias("flipped"), (F.col("features") == 0).alias("unsupported"), F.lit(False).alias("easy"), F.lit(fits).alias("fits"),
        )
        new = cut(new, f"round-{rounds}")
        stats = cut(graph.add_stats(stats, graph.feature_stats(incidence, F.broadcast(new.select("pair_id", "label")))), "stats")  # at most labels_per_round rows
        log = log.unionByName(new)
        if rounds % 10 == 0:
            log = cut(log, "log")
    return log


def resume_labels(log: DataFrame) -> DataFrame:
    """Labels so far, to be given as easy labels to a further run."""
    return log.select("pair_id", "label")


def label_items(items: DataFrame, incidence: DataFrame, easy: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """Another binary task on the same engine: items (item_id, score) instead of pairs."""
    renamed = lambda t: t.withColumnRenamed("item_id", "pair_id")
    out = label_kernel(renamed(items).withColumnRenamed("score", "sim"), renamed(incidence), renamed(easy), settings)
    return out.withColumnRenamed("pair_id", "item_id")
