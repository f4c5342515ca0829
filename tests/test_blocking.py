"""Groups of copies and frequent words: no similar pair is lost by blocking, and copies are not expanded."""

import hashlib
import itertools
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from pairlabel.functions import similarity as S
from pairlabel.operators import baselines as B
from pairlabel.operators import relational as R
from pairlabel.operators import vectors as V
from pairlabel.operators import workload as W
from pairlabel.plans import planner

WORDS = [f"w{i}" for i in range(9)]


def titles(shift=0):
    """A hot title, one that differs by a word, rare ones, one without tokens, one null, and repeated words."""
    rows = [(shift + i, WORDS[:6]) for i in range(40)] + [(shift + 40 + i, [*WORDS[:5], "w8"]) for i in range(30)]
    rows += [(shift + 70 + i, ["a", f"rare{i}", f"seldom{i}"]) for i in range(5)]
    return [*rows, (shift + 80, []), (shift + 81, None), (shift + 82, ["w0", "w0", *WORDS[1:6]])]


def table(spark, rows):
    return spark.createDataFrame(rows, "rec_id long, title array<string>")


def similar(a, b, t=0.5):
    a, b = set(a or ()), set(b or ())
    return bool(a | b) and len(a & b) >= t * len(a | b)


def ids(frame, *cols):
    return {tuple(r) for r in frame.select(*cols).collect()}


@pytest.mark.parametrize("across", [True, False])
def test_rest_loses_no_similar_pair(spark, across):
    rows_a = titles()
    rows_b = titles(1000) if across else rows_a
    a, b = table(spark, rows_a), table(spark, rows_b) if across else None
    found = ids(W.block_by_tokens(a, b, 5, 2) if across else W.block_within(a, 5, 2), "id_a", "id_b")
    rest = ids(W.block_rest(a, b, 5, 2), "id_a", "id_b")
    assert not rest & found
    sets = lambda t: t.select("rec_id", F.col("title").alias("s"))
    class_a = dict(ids(planner.token_classes(sets(a)), "rec_id", "class_id"))
    class_b = dict(ids(planner.token_classes(sets(b)), "rec_id", "class_id")) if across else class_a
    pairs = itertools.product(rows_a, rows_b) if across else itertools.combinations(rows_a, 2)
    want = {(x, y) for (x, s), (y, t) in pairs if similar(s, t)}
    linked = rest if across else rest | {(y, x) for x, y in rest} | {(c, c) for c in class_a.values()}
    assert {(x, y) for x, y in want if (x, y) not in found and (class_a[x], class_b[y]) not in linked} == set()
    assert {(x, y) for x, y in rest if not similar(dict(rows_a)[x], dict(rows_b)[y])} == set()
    assert len(rest) <= 4 and len(want - found) > 1000


def test_similar_classes_against_all_pairs(spark):
    rows = titles()
    got = ids(planner.similar_classes(table(spark, rows).withColumnRenamed("title", "s"), 0.5), "id_a", "id_b", "copy")
    copies = {(x, y) for x, y, copy in got if copy}
    root = {y: x for x, y in copies}
    links = {(x, y) for x, y, copy in got if not copy}
    for (x, s), (y, t) in itertools.combinations(rows, 2):
        a, b = root.get(x, x), root.get(y, y)
        assert similar(s, t) == ((a == b and bool(s)) or (min(a, b), max(a, b)) in links)


def test_empty_tables(spark):
    none = table(spark, [])
    assert W.block_rest(none, none).count() == 0 and W.block_rest(none).count() == 0
    assert planner.similar_classes(none.withColumnRenamed("title", "s"), 0.5).count() == 0


@pytest.mark.parametrize("threshold", [0.3, 0.5, 0.75, 1.0])
def test_prefix_join_is_exact(spark, threshold):
    rng = np.random.default_rng(3)
    sets = [sorted({f"t{int(k)}" for k in rng.zipf(1.3, 12) % 40}) for _ in range(120)]
    t = spark.createDataFrame(list(enumerate(sets)), "rec_id long, s array<string>")
    want = {(i, j) for i, j in itertools.combinations(range(len(sets)), 2) if similar(sets[i], sets[j], threshold)}
    assert ids(planner.prefix_join(t, t, threshold).where("id_a < id_b"), "id_a", "id_b") == want


def test_near_vectors_recall(spark, sf):
    e = W.load(spark, sf, "embeddings").where("embedding is not null").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v"))
    rows = sorted((r["id"], r["v"]) for r in e.collect())
    at, v = [r[0] for r in rows], np.array([r[1] for r in rows], dtype=float)
    far = np.sqrt(((v[:, None] - v[None]) ** 2).sum(-1))
    want = {(at[i], at[j]) for i, j in zip(*np.nonzero(np.triu(far <= 1.1, 1)), strict=True)}
    got = ids(V.near_vectors(e, e, 1.1, bucket=0.25).where("id_a < id_b"), "id_a", "id_b")
    assert want and got <= want and len(got) >= 0.9 * len(want)


def test_rule_cut_within_ties(spark):
    pairs = spark.createDataFrame([(i, 0.5) for i in range(10)] + [(10, 0.9), (11, 0.1)], "pair_id long, sim double")
    assert ids(B.rule_pairs(pairs, 0.34), "pair_id", "label") == {(i, int(i in (10, 0, 1, 2))) for i in range(12)}


def test_salted_join_repeats_hot_keys_alone(spark):
    left = spark.createDataFrame([(k, i) for i in range(60) for k in ((1,) if i < 40 else (2, None))], "k long, i long")
    right = spark.createDataFrame([(1, "a"), (1, "b"), (2, "c"), (3, "d"), (None, "e")], "k long, v string")
    out = R.salted_join(left, right, ["k"], 16, hot_rows=30)
    assert sorted(out.select("k", "i", "v").collect()) == sorted(left.join(right, "k").select("k", "i", "v").collect())
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        plan = R.salted_join(left, right, ["k"], 16, hot_rows=30)._jdf.queryExecution().executedPlan().toString()
        rows = R.salted_join(left, right.withColumn("v", F.monotonically_increasing_id()), ["k"], 16, hot_rows=1000)
    finally:
        spark.conf.unset("spark.sql.adaptive.enabled")
    assert "SortMergeJoin" in plan and rows.count() == 100  # no key is hot: no row of the right table is repeated


def test_range_join_names_classes_of_equal_prices(spark, sf, tmp_path):
    from pairlabel.queries import surface

    prices = [100.0, 100.0, 100.05, 100.2, None, 100.05, 900.0]
    spark.createDataFrame(list(enumerate(prices)), "p_partkey long, p_retailprice double").write.parquet(f"{tmp_path}/part.parquet")
    got = ids(surface.QUERIES["op_join_range"](spark, str(tmp_path)), "a", "b", "copy")
    name = {y: x for x, y, copy in got if copy}
    links = {(x, y) for x, y, copy in got if not copy}
    assert name == {1: 0, 5: 2}
    for (i, p), (j, q) in itertools.product([x for x in enumerate(prices) if x[1]], repeat=2):
        assert ((name.get(i, i), name.get(j, j)) in links) == (q * 0.999 <= p <= q * 1.001)


def test_sorted_neighbours_do_not_depend_on_the_sample(spark):
    """Range bounds come from a sample that every run draws anew."""
    n = 4000
    rows = spark.range(n).select(F.col("id").alias("rec_id"), F.md5(F.col("id").cast("string")).alias("k")).repartition(8)
    spark.conf.set("spark.sql.execution.rangeExchange.sampleSizePerPartition", "3")
    spark.conf.set("spark.sql.exchange.reuse", "false")
    try:
        got = sorted(tuple(r) for r in W.block_sorted(rows, F.col("k"), 2, 16).collect())
    finally:
        spark.conf.unset("spark.sql.execution.rangeExchange.sampleSizePerPartition")
        spark.conf.unset("spark.sql.exchange.reuse")
    order = [r.rec_id for r in sorted(rows.collect(), key=lambda r: (r.k, r.rec_id))]
    assert got == sorted((min(p), max(p)) for i in range(n) for p in ((order[i], order[j]) for j in range(i + 1, min(i + 3, n))))


@pytest.mark.parametrize("threshold", [0.3, 0.5, 0.75, 1.0])
def test_short_join_is_exact(spark, threshold):
    rng = np.random.default_rng(4)
    sets = sorted({tuple(sorted({f"t{int(k)}" for k in rng.zipf(1.3, 12) % 40})) for _ in range(150)})
    t = spark.createDataFrame([(i, list(s), 1 + i % 3) for i, s in enumerate(sets)], "rec_id long, s array<string>, n_records long")
    want = {(i, j) for i, j in itertools.product(range(len(sets)), repeat=2) if similar(sets[i], sets[j], threshold)}
    got = [tuple(r) for r in planner.short_join(t, t, threshold).select("id_a", "id_b").collect()]
    assert len(got) == len(set(got)) and set(got) == want
    df = {w: sum(1 + i % 3 for i, s in enumerate(sets) if w in s) for s in sets for w in s}
    common = {(i, j) for i, j in want if sum(df[w] <= 30 for w in set(sets[i]) & set(sets[j])) < 2}
    assert ids(planner.short_join(t, t, threshold, 30, 2), "id_a", "id_b") == common


def test_minhash_classes_do_not_expand_copies(spark):
    rows_a, rows_b = titles(), titles(1000)
    a, b = table(spark, rows_a), table(spark, rows_b)
    got = [tuple(r) for r in W.minhash_classes(a, b).collect()]
    assert len(got) == len(set(got)) < 250
    root = {(kind, y): x for x, y, kind in got if kind != "pair"}
    links = {(x, y) for x, y, kind in got if kind == "pair"}
    every = ids(W.block_minhash(a, b), "id_a", "id_b")
    assert len(every) > 2000
    for (x, s), (y, t) in itertools.product(rows_a, rows_b):
        assert ((x, y) in every) == ((root.get(("left", x), x), root.get(("right", y), y)) in links)


@pytest.mark.parametrize("block_rows", [7, 1000])
def test_label_agreement_counts_every_pair_once(spark, block_rows):
    rng = np.random.default_rng(6)
    v = rng.normal(size=(60, 4))
    v[3] = 0
    rows = [(i, f"b{i % 2}", v[i].tolist(), None if i == 8 else int(rng.integers(0, 3))) for i in range(60)]
    want = dict.fromkeys(("tp", "fp", "fn", "tn"), 0)
    for (_, p, x, a), (_, q, y, b) in itertools.combinations([r for r in rows if r[3] is not None], 2):
        if p == q:
            size = np.linalg.norm(x) * np.linalg.norm(y)
            over = size > 0 and np.dot(x, y) / size > 0.2
            want[("t" if over == (a == b) else "f") + ("p" if over else "n")] += 1
    got = V.label_agreement(spark.createDataFrame(rows, "id long, bucket string, v array<double>, label int"), 0.2, block_rows)
    assert got.first().asDict() == want and sum(want.values()) > 800


def components(n, edges):
    root = list(range(n))
    for x, y in edges:
        x, y = root[x], root[y]
        root = [min(x, y) if r in (x, y) else r for r in root]
    return root


def mixed_sets(rng):
    """Near copies of three texts, chains of drifting sets, unrelated sets with frequent words, copies, empty sets."""
    rows = []
    for size in (6, 30, 90):
        base = [f"b{size}_{i}" for i in range(size)]
        rows += [[w for w in base if rng.random() < 0.8] + [f"x{int(k)}" for k in rng.integers(0, 4000, size // 4)] for _ in range(25)]
    rows += [[f"c{i}" for i in range(k, k + 12)] for k in range(0, 60, 3)]
    rows += [[f"z{int(k)}" for k in rng.zipf(1.2, int(rng.integers(1, 60))) % 500] for _ in range(80)]
    return [*rows, [], [], rows[0], rows[0], [*rows[30], *rows[30]]]


@pytest.mark.parametrize(("threshold", "block", "numbered"), [(0.5, 10**9, 10**6), (0.5, 3000, 10**6), (0.5, 3000, 20), (0.3, 3000, 0), (0.8, 3000, 20), (1.0, 3000, 10**6)])
def test_links_keep_all_components(spark, monkeypatch, threshold, block, numbered):
    from pairlabel.plans import similar_sets

    rows = mixed_sets(np.random.default_rng(5))
    for name, value in (("links", {"block": block, "small": 10**9}), ("coded_sets", {"max_numbered": numbered})):
        monkeypatch.setattr(similar_sets, name, lambda *a, f=getattr(similar_sets, name), value=value: f(*a, **value))
    records = spark.createDataFrame(list(enumerate(rows)), "rec_id long, words array<string>")
    want = components(len(rows), [(i, j) for i, j in itertools.combinations(range(len(rows)), 2) if similar(rows[i], rows[j], threshold)])
    assert dict(ids(W.cluster_entities(records, threshold), "rec_id", "entity_id")) == dict(enumerate(want))


def test_links_do_not_list_near_copies(spark):
    """200 near copies are 19,900 links, of which a task gives at most 199: before, all were shuffled with their sets."""
    from pairlabel.plans import similar_sets

    rng = np.random.default_rng(6)
    sets = spark.createDataFrame([(i, [f"w{k}" for k in range(50) if rng.random() < 0.95] + [f"own{i}"]) for i in range(200)], "rec_id long, s array<string>")
    heads = similar_sets.coded_sets(sets)
    assert similar_sets.links(heads, 0.5).count() == 199
    none = spark.createDataFrame([], "rec_id long, words array<string>")
    assert W.cluster_entities(none).count() == 0


def test_bodies_are_compared_without_being_sent_to_pairs(spark):
    """A body of many pairs goes to them as token numbers; its words, and their number or order, do not matter. Tokens of one record alone, null and empty bodies count too."""
    def record(i, body):
        return (i, ["t"], body, "s", 1.0)

    bodies = [[f"x{k}" for k in range(300)], [f"x{k}" for k in range(150, 900, 3)], [*["x1"] * 9, "x2", "own"], [], None, [f"y{k}" for k in range(70_000)] + ["x2"]]
    schema = "rec_id long, title array<string>, body array<string>, source string, n_chars double"
    a = spark.createDataFrame([record(i, b) for i, b in enumerate(bodies)], schema)
    b = spark.createDataFrame([record(i, (b or [])[::-2]) for i, b in enumerate(bodies)] + [record(9, bodies[5][:30_000])], schema)
    blocked = spark.createDataFrame([(x, y) for x in range(6) for y in (0, 1, 2, 3, 4, 5, 9)], "id_a long, id_b long")
    out = W.compare(blocked, a, b)
    other = {r.rec_id: set(r.body) for r in b.collect()}
    for r in out.collect():
        x, y = set(bodies[r.id_a] or ()), other[r.id_b]
        assert r.sim_body == (len(x & y) / len(x | y) if x | y else 0.0), (r.id_a, r.id_b)
    assert out.count() == 42
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert "body" not in plan.replace("sim_body", "")  # before, whole bodies were joined to every pair


@pytest.mark.parametrize("most", [10, 10_000])
def test_shared_tokens_with_and_without_numbers(spark, most):
    from pairlabel.plans import similar_sets as SS

    sets = [[f"w{k}" for k in range(i, 40 * i, i)] for i in range(1, 9)]
    left, right = (spark.createDataFrame([(i, s) for i, s in enumerate(own)], "rec_id long, s array<string>") for own in (sets, sets[::-1]))
    a, b = (t.toPandas().set_index("rec_id").sort_index() for t in SS.coded_tables(SS.hashed_sets(left), SS.hashed_sets(right), max_numbered=most))
    got = SS.shared_tokens(*[t[c].map(bytes).tolist() for t in (a, b) for c in ("near", "far", "rest")])
    assert got.tolist() == [len(set(x) & set(y)) for x, y in zip(sets, sets[::-1], strict=True)]


@pytest.mark.parametrize("bands, rows", [(16, 2), (5, 1), (4, 3)])
def test_minimum_hashes_meet_by_numbers(spark, bands, rows):
    """Each pair that agrees in some band, once; what was earlier is told by plain comparisons, where before a function ran over a sequence for each meeting."""
    rng = np.random.default_rng(5)
    side = lambda at: [(at + i, sorted({f"t{int(k)}" for k in rng.zipf(1.4, 8) % 30})) for i in range(60)]
    rows_a, rows_b = side(0), side(1000)
    met = W.block_minhash(table(spark, rows_a), table(spark, rows_b), bands=bands, rows=rows)
    plan = met._jdf.queryExecution().optimizedPlan().toString()
    assert "exists(" not in plan and "sequence(" not in plan

    def hashes(title):
        codes = [int(hashlib.md5(t.encode()).hexdigest()[:8], 16) for t in title]
        least = [min((c * a + b) % W.MINHASH_PRIME for c in codes) for a, b in map(W.minhash_step, range(bands * rows))]
        return [tuple(least[k * rows : (k + 1) * rows]) for k in range(bands)]

    a, b = ({i: hashes(t) for i, t in r} for r in (rows_a, rows_b))
    want = {(i, j) for i in a for j in b if any(x == y for x, y in zip(a[i], b[j], strict=True))}
    got = [tuple(r) for r in met.collect()]
    assert len(got) == len(set(got)) and set(got) == want and 0 < len(want) < 3600


def test_titles_split_no_whole_texts(spark):
    """Titles, also of the twin, come from the first parts of a text; they are those of all tokens."""
    texts = ["", None, " ", "one", "-- A b C", "a " * 12, " ".join(f"W{i}" for i in range(40)), "...x" * 13, "ünï, cødé! " * 9, "--".join(f"word{i}" for i in range(13)), "\n".join(f"word{i}" for i in range(14)), " lead " + "x y " * 7]
    docs = spark.createDataFrame([(k, t, "s", 5) for k, t in enumerate(texts)], "doc_id long, text string, source string, n_chars int")
    left = W.document_records(docs)
    for t in (left, W.corrupt(left)):
        plan = t.select("rec_id", "title")._jdf.queryExecution().optimizedPlan().toString()
        assert ", 14)" in plan and ", -1)" not in plan
        assert all(r.title + r.body == r.words and r.title == r.words[: len(r.title)] and len(r.title) <= 12 for r in t.collect())
    every = docs.select("doc_id", S.tokens(F.col("text")).alias("t"))
    assert {r.rec_id: (r.title, r.words) for r in left.collect()} == {r.doc_id: (r.t[:12], r.t) for r in every.collect()}
    loses = lambda r, i: (r * 7919 + i * 104729 + r * i * 31) % 100 < 5 + (r * 31) % 60
    drops = lambda r, i, w: w[0] + w[2:] if (r * 13 + i * 17) % 10 == 0 and len(w) > 3 else w
    for r in W.corrupt(left).collect():
        t = [w.lower() for w in re.findall(r"[^\W_]+", texts[r.rec_id] or "")]
        own = [drops(r.rec_id, i, w) for i, w in enumerate(t) if not loses(r.rec_id, i)]
        assert r.words == own and r.title == own[: len(r.title)]
