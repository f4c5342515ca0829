"""Baselines: clustering, the rule cut, a linear SVM and a neural classifier."""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml import Pipeline
from pyspark.ml.classification import LinearSVC, MultilayerPerceptronClassifier
from pyspark.ml.clustering import KMeans
from pyspark.ml.feature import PolynomialExpansion, VectorAssembler
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.planner import cut
from . import easy as E
from . import metrics as M
from .workload import PARTS


def cluster_pairs(pairs: DataFrame, cols: tuple[str, ...] = PARTS, seed: int = 42) -> DataFrame:
    """pair_id, label by k-means with two classes; the one with the greater centre is match."""
    data = VectorAssembler(inputCols=list(cols), outputCol="features").transform(pairs.select("pair_id", *cols))
    model = KMeans(k=2, seed=seed, featuresCol="features", predictionCol="c").fit(data)
    sums = [float(c.sum()) for c in model.clusterCenters()]
    return model.transform(data).select("pair_id", (F.col("c") == sums.index(max(sums))).cast("int").alias("label"))


def fixed_centres(pairs: DataFrame, cols: tuple[str, ...] = PARTS, rounds: int = 10) -> list[dict[str, float]]:
    """Two centres from the columns' least and greatest values by so many steps; an empty cluster keeps its centre. Each step is one aggregate of two rows."""
    r = pairs.agg(*[F.min(c).alias(f"lo_{c}") for c in cols], *[F.max(c).alias(f"hi_{c}") for c in cols]).first()
    centres = [{c: r[f"{s}_{c}"] or 0.0 for c in cols} for s in ("lo", "hi")]
    for _ in range(rounds):
        got = {g["k"]: g for g in pairs.groupBy(nearest(centres).alias("k")).agg(*[F.avg(c).alias(c) for c in cols]).collect()}
        centres = [{c: got[k][c] for c in cols} if k in got else centres[k] for k in (0, 1)]
    return centres


def nearest(centres: list[dict[str, float]]):
    d = [sum(((F.col(c) - v) * (F.col(c) - v) for c, v in centre.items()), F.lit(0.0)) for centre in centres]
    return (d[1] < d[0]).cast("int")


def cluster_pairs_fixed(pairs: DataFrame, cols: tuple[str, ...] = PARTS, rounds: int = 10) -> DataFrame:
    return pairs.select("pair_id", nearest(fixed_centres(pairs, cols, rounds)).alias("label"))


def match_share(pairs: DataFrame, rounds: int = 10) -> float:
    return cluster_pairs_fixed(pairs, rounds=rounds).agg(F.coalesce(F.avg("label"), F.lit(0.0))).first()[0]


def rule_pairs(pairs: DataFrame, share: float | None = None) -> DataFrame:
    """Cut by similarity at the k-means share."""
    share = match_share(pairs) if share is None else share
    matches = E.extremes(pairs, int(pairs.count() * share + 1e-9), 0)
    return pairs.select("pair_id").join(matches, "pair_id", "left").select("pair_id", F.coalesce("label", F.lit(0)).alias("label"))


def split(pairs: DataFrame, run: int, *shares: float):
    """Column: number of the part (0 first, len(shares): the rest) by a hash of pair and run."""
    u = F.pmod(F.xxhash64("pair_id", F.lit(run)), F.lit(1_000_000)) / 1e6
    out, at = F.lit(len(shares)), sum(shares)
    for k in reversed(range(len(shares))):
        out = F.when(u < at, k).otherwise(out)
        at -= shares[k]
    return out


def svm_pairs(pairs: DataFrame, truth: DataFrame, train: float, runs: int = 10, cols: tuple[str, ...] = PARTS) -> DataFrame:
    """run, precision, recall, f1 on what was not used for training; classes are weighted, a quadratic expansion stands in for the kernel."""
    out = None
    data = cut(pairs.select("pair_id", *cols).join(truth, "pair_id"), "svm-data")
    for run in range(runs):
        parted = data.withColumn("part", split(data, run, train))
        balance = parted.where("part = 0").agg(F.avg("truth")).first()[0]
        if not balance or balance == 1.0:
            continue
        rows = parted.withColumn("w", F.when(F.col("truth") == 1, 0.5 / balance).otherwise(0.5 / (1 - balance)))
        stages = [VectorAssembler(inputCols=list(cols), outputCol="v"), PolynomialExpansion(degree=2, inputCol="v", outputCol="features"), LinearSVC(labelCol="truth", weightCol="w", maxIter=30, regParam=0.001)]
        model = Pipeline(stages=stages).fit(rows.where("part = 0"))
        test = model.transform(rows.where("part = 1")).select("pair_id", F.col("prediction").cast("int").alias("label"))
        one = M.quality(test, truth).select(F.lit("svm").alias("method"), F.lit(run).alias("run"), "precision", "recall", "f1")
        out = one if out is None else out.unionAll(one)
    return out


def mlp_pairs(pairs: DataFrame, truth: DataFrame, train: float, valid: float = 0.05, runs: int = 10, layers: tuple[tuple[int, ...], ...] = ((8,), (16, 8)), cols: tuple[str, ...] = PARTS, dims: int = 8, seed: int = 42) -> DataFrame:
    """run, precision, recall, f1: a perceptron on hashed title vectors (their difference and product) and similarities; the validation part picks the layers."""

    def hashed(c: str):
        slot = lambda k: F.size(F.filter(F.col(c), lambda t: F.pmod(F.xxhash64(t), F.lit(dims)) == k)) / F.greatest(F.size(c), F.lit(1))
        return [slot(k) for k in range(dims)]

    a, b = hashed("title_a"), hashed("title_b")
    extra = [f"d{k}" for k in range(dims)] + [f"m{k}" for k in range(dims)]
    data = pairs.select("pair_id", *cols, *[F.abs(x - y).alias(f"d{k}") for k, (x, y) in enumerate(zip(a, b, strict=True))], *[(x * y).alias(f"m{k}") for k, (x, y) in enumerate(zip(a, b, strict=True))])
    data = VectorAssembler(inputCols=[*cols, *extra], outputCol="features").transform(data).select("pair_id", "features").join(truth, "pair_id")
    data = cut(data, "mlp-data")
    out = None
    for run in range(runs):
        rows = data.withColumn("part", split(data, run, train, valid))
        best = None
        for hidden in layers:
            model = MultilayerPerceptronClassifier(labelCol="truth", layers=[len(cols) + len(extra), *hidden, 2], maxIter=60, seed=seed + run).fit(rows.where("part = 0"))
            v = M.f1(model.transform(rows.where("part = 1")).select("pair_id", F.col("prediction").cast("int").alias("label")), truth).first()[0]
            best = max(best or (-1.0, None), (v, model), key=lambda t: t[0])
        test = best[1].transform(rows.where("part = 2")).select("pair_id", F.col("prediction").cast("int").alias("label"))
        one = M.quality(test, truth).select(F.lit("mlp").alias("method"), F.lit(run).alias("run"), "precision", "recall", "f1")
        out = one if out is None else out.unionAll(one)
    return out


# many runs at once, over tables of any size


def _wide(x: np.ndarray, mean: np.ndarray, scale: np.ndarray) -> np.ndarray:
    """The quadratic expansion of scaled rows, with a constant."""
    upper = np.triu_indices(x.shape[1])
    z = (x - mean) / scale
    return np.column_stack([z, z[:, upper[0]] * z[:, upper[1]], np.ones(len(z))])


def train_svms(data: DataFrame, tasks: list[tuple[float, int]], regular: float = 1e-3, rounds: int = 25) -> list[tuple]:
    """Classifiers, one for each (share, run): squared hinge with balanced classes on a quadratic expansion, by Newton steps. The data stay where they are: a step of all runs is one pass that sums gradients and Hessians, whose size does not grow with the rows."""
    runs = max(r for _, r in tasks) + 1

    def sums(of, needed: list[int]) -> dict[int, list[np.ndarray]]:
        """Sums over all rows of what ``of`` gives for the training rows of each needed task."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict[int, list] = {}
            for x, y, drawn in _rows(batches):
                for k in needed:
                    share, r = tasks[k]
                    own = drawn[:, r] / 1e6 < share
                    if own.any():
                        got = of(k, x[own], y[own])
                        total[k] = [a + b for a, b in zip(total[k], got, strict=True)] if k in total else got
            yield pa.RecordBatch.from_pydict({"task": pa.array(list(total), pa.int32()), "part": pa.array([pickle.dumps(v) for v in total.values()], pa.binary())})

        out: dict[int, list] = {}
        for r in sorted(with_draws(data, runs).mapInArrow(run, "task int, part binary").collect()):
            part = pickle.loads(r["part"])
            out[r["task"]] = [a + b for a, b in zip(out[r["task"]], part, strict=True)] if r["task"] in out else part
        return out

    every = list(range(len(tasks)))
    counted = sums(lambda k, x, y: [len(x), int((y > 0).sum()), x.sum(0)], every)
    means = {k: s / n for k, (n, _, s) in counted.items()}
    spread = sums(lambda k, x, y: [((x - means[k]) ** 2).sum(0)], [k for k in every if k in means])
    scales = {k: np.sqrt(v[0] / counted[k][0]) + 1e-9 for k, v in spread.items()}
    left = {k for k, (n, ones, _) in counted.items() if 0 < ones < n}
    w = {k: np.zeros(len(_wide(means[k][None], means[k], scales[k])[0])) for k in left}
    for _ in range(rounds):
        if not left:
            break

        def step(k: int, x: np.ndarray, y: np.ndarray) -> list[np.ndarray]:
            n, ones, _ = counted[k]
            a, sign = _wide(x, means[k], scales[k]), np.where(y > 0, 1.0, -1.0)
            gap = 1 - sign * (a @ w[k])
            on = gap > 0
            weight = np.where(y[on] > 0, 0.5 / ones, 0.5 / (n - ones))
            return [a[on].T @ (weight * sign[on] * gap[on]), (a[on] * weight[:, None]).T @ a[on]]

        for k, (g, h) in sums(step, sorted(left)).items():
            move = np.linalg.solve(h + regular * np.eye(len(g)), regular * w[k] - g)
            w[k] = w[k] - move
            if np.abs(move).max() < 1e-9:
                left.discard(k)
    one_class = {k: int(n > 0 and ones / n >= 0.5) for k, (n, ones, _) in counted.items()}
    return [("svm", means[k], scales[k], w[k]) if k in w else ("same", one_class.get(k, 0)) for k in every]


def _forward(par: list[np.ndarray], z: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    kept = [z]
    for k in range(0, len(par) - 2, 2):
        z = np.maximum(z @ par[k] + par[k + 1], 0)
        kept.append(z)
    return kept, 1 / (1 + np.exp(-np.clip((z @ par[-2] + par[-1])[:, 0], -60, 60)))


def _views(flat: np.ndarray, shapes: list[tuple[int, ...]]) -> list[np.ndarray]:
    at = np.cumsum([0, *(int(np.prod(s)) for s in shapes)]).tolist()
    return [flat[a:b].reshape(s) for a, b, s in zip(at, at[1:], shapes, strict=False)]


def _over_rows(x: np.ndarray, of, step: int = 4096) -> np.ndarray:
    """The sum over rows of what ``of`` gives, without a second array of that size."""
    total = np.zeros((1, x.shape[1]))
    for k in range(0, len(x), step):
        total = np.concatenate([total, of(x[k : k + step])]).sum(0, keepdims=True)
    return total[0]


def train_mlp(x: np.ndarray, y: np.ndarray, valid: tuple[np.ndarray, np.ndarray], layers: tuple[tuple[int, ...], ...] = ((16,), (32, 16)), epochs: int = 80, batch: int = 64, rate: float = 3e-3, seed: int = 42) -> tuple:
    """A classifier: a perceptron with rectified layers and Adam steps; the validation part picks layers and epoch by F1. x is scaled in place, and all parameters of a perceptron are parts of one array, so a step of Adam is a few operations."""
    mean = _over_rows(x, lambda part: part) / len(x)
    scale = np.sqrt(_over_rows(x, lambda part: (part - mean) ** 2) / len(x)) + 1e-9
    x -= mean
    x /= scale
    rng = np.random.default_rng(seed)
    checked, truth = (valid[0] - mean) / scale, valid[1] > 0

    def f1(par) -> float:
        got = _forward(par, checked)[1] >= 0.5
        return 2 * (got & truth).sum() / max(1, got.sum() + truth.sum())

    best = (-1.0, None)
    for hidden in layers:
        sizes = [x.shape[1], *hidden, 1]
        first = [p for a, b in zip(sizes, sizes[1:], strict=False) for p in (rng.normal(0, np.sqrt(2 / a), (a, b)), np.zeros(b))]
        shapes = [p.shape for p in first]
        flat = np.concatenate([p.ravel() for p in first])
        g = np.zeros_like(flat)
        par, grads = _views(flat, shapes), _views(g, shapes)
        m1, m2, t = np.zeros_like(flat), np.zeros_like(flat), 0
        for epoch in range(epochs):
            order = rng.permutation(len(x))
            for at in range(0, len(order), batch):
                own = order[at : at + batch]
                kept, p = _forward(par, x[own])
                d = ((p - y[own]) / len(own))[:, None]
                for k in range(len(par) - 2, -1, -2):
                    z = kept[k // 2]
                    np.matmul(z.T, d, out=grads[k])
                    d.sum(0, out=grads[k + 1])
                    if k:
                        d = (d @ par[k].T) * (z > 0)
                t += 1
                m1 *= 0.9
                m1 += 0.1 * g
                m2 *= 0.999
                m2 += 0.001 * g * g
                flat -= rate * (m1 / (1 - 0.9**t)) / (np.sqrt(m2 / (1 - 0.999**t)) + 1e-8)
            if epoch % 4 == 3 and (score := f1(par)) > best[0]:
                best = (score, [p.copy() for p in par])
    return "mlp", mean, scale, best[1]


def train_mlps(data: DataFrame, tasks: list[tuple[float, int]], valid: float) -> list[tuple]:
    """Classifiers, one for each (share, run), each from a task that reads the data for itself and keeps what its run trains and validates on: nothing is shuffled, and no process holds all rows."""

    def learner(k: int):
        share, r = tasks[k]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            parts = [(b.column("pair_id").to_numpy(), b.column("drawn").to_numpy(), b.column("truth").to_numpy(), *(_flat(b, c) for c in ("x", "slots_a", "slots_b"))) for b in batches if b.num_rows]
            if parts:
                ids, drawn, y, *held = (np.concatenate(p) for p in zip(*parts, strict=True))
                del parts
                order = np.lexsort((ids, drawn))
                u, y = drawn[order] / 1e6, y[order]
                n = int(np.searchsorted(u, share - valid))
                if len(set(y[:n].tolist())) == 2:
                    check = _inputs(*(h[order[n:]] for h in held)), y[n:]
                    x = _inputs(*(h[order[:n]] for h in held))
                    del held
                    model = train_mlp(x, y[:n], check, seed=42 + r)
                else:
                    model = "same", int(n > 0 and y[:n].mean() >= 0.5)
                yield pa.RecordBatch.from_pydict({"task": pa.array([k], pa.int32()), "model": pa.array([pickle.dumps(model)], pa.binary())})

        own = F.pmod(F.xxhash64("pair_id", F.lit(r)), F.lit(1_000_000)).cast("int")
        rows = data.withColumn("drawn", own).where(F.col("drawn") / 1e6 < share)
        return rows.coalesce(1).mapInArrow(run, "task int, model binary")

    out = None
    for k in sorted(range(len(tasks)), key=lambda k: -tasks[k][0]):  # the longest first
        out = learner(k) if out is None else out.unionAll(learner(k))
    got = {r["task"]: pickle.loads(r["model"]) for r in out.collect()}
    return [got.get(k, ("same", 0)) for k in range(len(tasks))]


def predict(model: tuple, x: np.ndarray) -> np.ndarray:
    """0 or 1 for each row."""
    kind, *of = model
    if kind == "svm":
        return (_wide(x, *of[:2]) @ of[2] >= 0).astype(int)
    if kind == "mlp":
        return (_forward(of[2], (x - of[0]) / of[1])[1] >= 0.5).astype(int)
    return np.full(len(x), of[0])


def _slots(c: str, dims: int):
    """How many tokens of an array fall into each slot, and how many it has."""
    slot = F.transform(c, lambda t: F.pmod(F.xxhash64(t), F.lit(dims)))
    return F.transform(F.sequence(F.lit(0), F.lit(dims)), lambda k: F.when(k == dims, F.size(c)).otherwise(F.size(F.filter(slot, lambda s: s == k))).cast("short"))


def _flat(b: pa.RecordBatch, c: str) -> np.ndarray:
    return b.column(c).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)


def _inputs(x: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Similarities, and difference and product of title vectors from counts of a title's tokens in each slot, the last of all of them."""
    a, b = (z[:, :-1] / np.maximum(z[:, -1:], 1) for z in (a, b))
    return np.concatenate([x, np.abs(a - b), a * b], axis=1)


def with_draws(data: DataFrame, runs: int) -> DataFrame:
    """drawn: of each run a number below a million that decides to which part a pair belongs; made where it is read."""
    return data.withColumn("drawn", F.array(*[F.pmod(F.xxhash64("pair_id", F.lit(r)), F.lit(1_000_000)).cast("int") for r in range(runs)]))


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Inputs of a classifier, truth and draws."""
    for b in batches:
        if b.num_rows:
            x = _flat(b, "x")
            if "slots_a" in b.schema.names:
                x = _inputs(x, _flat(b, "slots_a"), _flat(b, "slots_b"))
            yield x, b.column("truth").to_numpy(), _flat(b, "drawn")


def supervised_runs(pairs: DataFrame, truth: DataFrame, method: str, shares: tuple[float, ...] = (0.1, 0.2, 0.3), runs: int = 10, valid: float = 0.05, cols: tuple[str, ...] = PARTS, dims: int = 24) -> DataFrame:
    """method, share, run, precision, recall, f1 of svm or mlp on what was not used for training; all runs at all shares from one written table, which is never collected or shuffled. Only classifiers and counts come to the driver.

    mlp also sees hashed title vectors (their difference and product), and of its share ``valid`` validates; a run's training part is in one task, with Adam steps in sequence.
    """
    spark = pairs.sparkSession
    schema = "method string, share double, run int, precision double, recall double, f1 double"
    data = pairs.select("pair_id", F.array(*cols).alias("x"), *([_slots(f"title_{s}", dims).alias(f"slots_{s}") for s in "ab"] if method == "mlp" else [])).join(truth, "pair_id")
    data = cut(data, f"{method}-runs")
    tasks = [(s, r) for s in shares for r in range(runs)]
    if not data.limit(1).count():
        return spark.createDataFrame([], schema)
    models = train_svms(data, tasks) if method == "svm" else train_mlps(data, tasks, valid)
    sent = spark.sparkContext.broadcast(models)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((len(tasks), 3), np.int64)
        for x, y, drawn in _rows(batches):
            for k, (share, r) in enumerate(tasks):
                test = drawn[:, r] / 1e6 >= share
                got, real = predict(sent.value[k], x[test]) > 0, y[test] > 0
                counts[k] += (got & real).sum(), got.sum(), real.sum()
        yield pa.RecordBatch.from_arrays([pa.array(range(len(tasks)), pa.int32()), *map(pa.array, counts.T)], ["task", "tp", "got", "real"])

    total = with_draws(data, runs).mapInArrow(score, "task int, tp long, got long, real long").groupBy("task").agg(*[F.sum(c).alias(c) for c in ("tp", "got", "real")])
    out = []
    for k, tp, got, real in sorted(map(tuple, total.collect())):
        p, r = tp / max(1, got), tp / max(1, real)
        out.append((method, *tasks[k], p, r, 2 * p * r / (p + r) if p + r else 0.0))
    return spark.createDataFrame(out, schema)
