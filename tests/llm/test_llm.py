"""The ten operators against brute force, exact round trips and held-out accuracy, and on odd inputs."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers as P
import pytest
from tokenizers import Tokenizer

from pairlabel.llm import ann_tree, bin_packing, bit_packing, bpe, chat_format, exact_dedup, language_model, license_scan, near_duplicates, toxicity
from pairlabel.llm.tokens import WordEncoder

BYTE, WORD = P.path("byte_bpe_50k.json"), P.path("word_bpe_49k.json")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, digest string, n int, block int"
ODD = [None, "", "   \n\t", "One", "one", "ONE", "É é Σ İ ß", "a" * 9000, "x y " * 30_000, "<|endoftext|> hi", "cc by all rights reserved", "one", "日本語 かな", "a\x00b\x85c"]


def lower(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and long texts, repeated rows and ids, clashing columns."""
    rows = [(i, t, None, "s", None, "d", 1, 1) for i, t in enumerate(ODD)] + [(3, "One", None, None, 1, "d", 1, 1), (None, "lost", None, None, None, None, None, None), (None, None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


def brute_sets(rows):
    out = []
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", lower(t))
        out.append((i, {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())))
    return out


def brute_components(rows):
    sets = [(i, s) for i, s in brute_sets(rows) if i is not None]
    root = {i: i for i, _ in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for k, (a, s) in enumerate(sets):
        for b, t in sets[:k]:
            if s and t and 100 * len(s & t) >= 75 * len(s | t):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i in root}


def check_components(df, rows, **grouping):
    want, sizes = brute_components(rows), Counter((i, len(s)) for i, s in brute_sets(rows))
    got = near_duplicates.jaccard_components(df, **grouping).collect()
    assert Counter((r.doc_id, r.n_shingles) for r in got) == sizes
    for r in got:
        assert r.component_id == (want[r.doc_id] if r.doc_id is not None else None)


def test_near_duplicates_documents(docs):
    check_components(docs, [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()])


def test_near_duplicates_odd(odd, none):
    check_components(odd, [(r.doc_id, r.text) for r in odd.collect()])
    assert near_duplicates.jaccard_components(none).count() == 0


def test_near_duplicates_hard(spark):
    """Chains, near copies around the threshold, shared passages, hot groups."""
    rnd = random.Random(5)
    word = lambda: "".join(rnd.choice("abcdefgh") for _ in range(4))
    passage = [word() for _ in range(60)]
    rows, n = [], 0
    for _ in range(12):
        base = [word() for _ in range(rnd.choice([8, 30, 80, 200]))]
        if rnd.random() < 0.5:
            base = passage + base[:30]
        for _ in range(rnd.choice([1, 3, 12])):
            mine = list(base)
            for _ in range(rnd.choice([0, 1, 1, 2, 3])):
                mine[rnd.randrange(len(mine))] = word()
            rows.append((n, " ".join(mine)))
            n += 1
            base = mine if rnd.random() < 0.4 else base  # drifting away
    rows += [(n + k, " ".join(passage + [word() for _ in range(rnd.randint(2, 14))])) for k in range(60)]
    df = spark.createDataFrame([(a, b) for a, b in rows], "doc_id long, text string").repartition(3)
    assert len(set(brute_components(rows).values())) < len(rows)
    check_components(df, rows)
    check_components(df, rows, leaders=0)  # every link must then come from the matrix
    check_components(df, rows, leaders=1, salts=2, block_rows=2, part_rows=3)


def test_busy_blocks_are_split(spark):
    """Many documents ask one block: every share of them meets all of its members."""
    token = lambda *ids: np.array(sorted(ids), np.uint64).tobytes()
    common = range(100, 130)
    sets = [(k, 31, 1, 0, token(k, *common)) for k in range(3)] + [(10 + k, 31, 10 + k, 0, token(10 + k, *common)) for k in range(40)]
    sets += [(60 + k, 31, 60 + k, 0, token(60 + k, *range(120, 150))) for k in range(5)]
    df = spark.createDataFrame(sets, "rid long, n long, grp long, part int, tokens binary")
    links = {(r.grp, r.other) for r in near_duplicates.matrix_links(df, ask_rows=4).collect()}
    root = {g: g for _, _, g, _, _ in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in links:
        root[find(a)] = find(b)
    assert len({find(g) for g in root}) == 2 and all((a < 60) == (b < 60) for a, b in links)


def test_drop_near_copies(docs):
    want = brute_components([(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()])
    kept = near_duplicates.drop_near_copies(docs)
    assert kept.columns == docs.columns
    assert sorted(r.doc_id for r in kept.collect()) == sorted({i for i, c in want.items() if i == c})


def test_exact_dedup(docs, odd, none):
    for df in (docs, odd):
        rows = [(r.doc_id, lower(r.text)) for r in df.select("doc_id", "text").collect()]
        size, keep = Counter(t for _, t in rows), {}
        for i, t in rows:
            keep[t] = i if keep.get(t) is None or (i is not None and i > keep[t]) else keep[t]
        want = Counter((i, keep[t], size[t], i == keep[t], hashlib.sha256(t.encode()).hexdigest()) for i, t in rows)
        assert Counter(tuple(r) for r in exact_dedup.exact_dedup(df).collect()) == want
    assert exact_dedup.exact_dedup(none).count() == 0
    assert exact_dedup.drop_copies(none).count() == 0
    for df in (docs, odd, spark_rows(docs, [(1, "a"), (1, "a"), (1, "A"), (5, "b"), (7, "A"), (7, "b"), (None, "n"), (None, "N"), (5, None), (5, "")])):
        rows = [(r.doc_id, lower(r.text)) for r in df.select("doc_id", "text").collect()]
        keep = {}
        for i, t in rows:
            keep[t] = i if keep.get(t) is None or (i is not None and i > keep[t]) else keep[t]
        kept = exact_dedup.drop_copies(df)
        assert kept.columns == df.columns
        assert sorted(((lower(r.text), r.doc_id) for r in kept.collect()), key=str) == sorted(keep.items(), key=str)


def spark_rows(like, rows):
    return like.sparkSession.createDataFrame(rows, "doc_id long, text string")


def test_word_encoder_and_transducer():
    rnd = random.Random(3)
    libs = {p: Tokenizer.from_file(p) for p in (BYTE, WORD)}
    fast, t = {p: WordEncoder(p) for p in libs}, bpe.Transducer(BYTE)
    texts = [x or "" for x in ODD]
    for _ in range(300):
        alphabet = rnd.choice(["ab", "the 's", "aàéß ' s", "abc\n \t'sdn12", "\x85\xa0\x1c ax", "日本語 か", "éÉÇΣσς İı", "½²ªº_-."])
        texts.append("".join(rnd.choice(alphabet) for _ in range(rnd.randint(0, 200))))
    for x in texts:
        for p, lib in libs.items():
            ids = lib.encode(x, add_special_tokens=False).ids
            assert np.frombuffer(fast[p].encode(x), "<u4").tolist() == ids, (p, x[:50])
        ids = libs[BYTE].encode(x, add_special_tokens=False).ids
        assert t.encode(x).tolist() == ids
        assert t.decode(np.array(ids)) == libs[BYTE].decode(ids, skip_special_tokens=False)
    assert t.decode(np.array([t.single[0xE9]])) == libs[BYTE].decode([t.single[0xE9]], skip_special_tokens=False)


def test_transducer_streams_long_words():
    rnd = random.Random(4)
    lib, t = Tokenizer.from_file(BYTE), bpe.Transducer(BYTE)
    t.window = 2 * t.lookahead
    for parts in (["a"], ["in", "an", "tion", "er", "s", "re", "th", "e"], list("abcdefghijklmnopqrstuvwxyz"), ["é", "a"]):
        x = "".join(rnd.choice(parts) for _ in range(4000)).encode()
        ids = list(t.stream(x[k : k + 97] for k in range(0, len(x), 97)))
        assert ids == lib.encode(x.decode(), add_special_tokens=False).ids
    with pytest.raises(ValueError):
        bpe.Transducer(WORD)


def test_every_word_goes_through_the_transducer(docs):
    t, seen = bpe.Transducer(BYTE), []
    merged, stream = t.merge, t.stream
    inside = []
    t.stream = lambda chunks: (seen.append(b"".join(own := list(chunks))), inside.append(1), *stream(own), inside.pop())[2:-1]
    t.merge = lambda data: merged(data) if inside else pytest.fail("a word was merged past the transducer")
    texts = [r.text or "" for r in docs.collect()]
    words = {w for x in texts for part in (t.special_at.split(x)[::2] if t.special_at else [x]) for w in t.words.findall(part)}
    for x in texts:
        t.encode(x)
    assert {s.decode() for s in seen} == words and len(words) > 1000


def test_round_trip(docs, odd, none):
    lib = Tokenizer.from_file(BYTE)
    for df in (docs, odd):
        texts = [(r.doc_id, r.text or "") for r in df.select("doc_id", "text").collect()]
        want = Counter()
        for i, x in texts:
            ids = lib.encode(x, add_special_tokens=False).ids
            back = lib.decode(ids, skip_special_tokens=False)
            want[i, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(back.encode()).hexdigest()] += 1
        assert Counter(tuple(r) for r in bpe.round_trip(df, BYTE).collect()) == want
    encoded = bpe.encode_documents(odd, BYTE)
    assert Counter(r.text for r in bpe.decode_documents(encoded, BYTE).collect()) == Counter(x or "" for x in [r.text for r in odd.collect()])
    assert bpe.round_trip(none, BYTE).count() == 0


@pytest.mark.parametrize("width", [1, 3, 8, 11, 16, 17, 32])
def test_bit_packing(width):
    ids = np.random.default_rng(width).integers(0, 1 << width, 1000)
    packed = bit_packing.pack(ids, width)
    assert len(packed) == -(-1000 * width // 8)
    assert bit_packing.unpack(packed, width, 0, 1000).tolist() == ids.tolist()
    assert bit_packing.unpack(packed, width, 333, 7).tolist() == ids[333:340].tolist()
    assert bit_packing.unpack(packed, width, 1000, 0).tolist() == []


def test_bit_packed_corpus(docs, odd, none):
    lib = Tokenizer.from_file(WORD)
    for df in (docs, odd):
        rows = sorted(((r.doc_id, r.text or "") for r in df.select("doc_id", "text").collect()), key=lambda r: (r[0] is not None, r[0] or 0))
        blocks = bit_packing.pack_corpus(df, WORD, 2, block_ids=500)
        got = sorted(bit_packing.read_documents(blocks).collect(), key=lambda r: r.start)
        assert [r.doc_id for r in got] == [i for i, _ in rows]
        at = 0
        for r in got:
            assert r.start == at
            at += r.n_tokens
        want = Counter(tuple(lib.encode(x, add_special_tokens=False).ids + [2]) for _, x in rows)
        assert Counter(tuple(np.frombuffer(r.ids, "<u4").tolist()) for r in got) == want
    blocks = bit_packing.pack_corpus(odd, WORD, 2, block_ids=500)
    assert bit_packing.read_document(blocks, 4).tolist() == lib.encode("one", add_special_tokens=False).ids + [2]
    assert bit_packing.read_document(blocks, 99) is None
    whole = np.concatenate([np.frombuffer(r.ids, "<u4") for r in sorted(bit_packing.read_documents(blocks).collect(), key=lambda r: r.start)])
    for start, n in ((0, 1), (3, 700), (len(whole) - 5, 50), (1200, 4000), (len(whole), 3)):
        assert bit_packing.read_span(blocks, start, n).tolist() == whole[start : start + n].tolist()
    assert bit_packing.read_documents(bit_packing.pack_corpus(none, WORD, 2)).count() == 0


def one_by_one(lengths, cap):
    """Best fit placed piece by piece: least norm of what is left of all three capacities, each weighted and as a share of its limit."""
    bins, limits = [], [float(x) for x in cap.limits()]
    for n in sorted(lengths, reverse=True):
        fits = [k for k, (t, d, a) in enumerate(bins) if t >= n and d >= 1 and a >= n * n]
        if fits:
            k = min(fits, key=lambda k: sum((w * (left - use) / top) ** 2 for w, left, use, top in zip(cap.weights, bins[k], (n, 1, n * n), limits, strict=True)))
        else:
            bins.append([float(x) for x in cap.limits()])
            k = len(bins) - 1
        bins[k] = [bins[k][0] - n, bins[k][1] - 1, bins[k][2] - n * n]
    return len(bins)


@pytest.mark.parametrize("cap", [bin_packing.Capacity(64), bin_packing.Capacity(64, docs=4), bin_packing.Capacity(64, attention=2200.0), bin_packing.Capacity(64, docs=6, weights=(1.0, 0.0, 0.0)), bin_packing.Capacity(64, docs=3, attention=2500.0, weights=(0.5, 1.0, 2.0)), bin_packing.Capacity(64, docs=5, mode="dot", weights=(1.0, 0.5, 0.5))])
def test_pack_histogram(cap):
    rnd = random.Random(1)
    for _ in range(20):
        lengths = [rnd.choice([1, 3, 7, 20, 31, 33, rnd.randint(1, 46)]) for _ in range(rnd.randint(0, 200))]
        slots, used = bin_packing.pack_histogram(Counter(lengths), cap)
        bins, seen = {}, Counter()
        for n, first, pieces, sequence, per, offset in slots:
            for r in range(pieces):
                bins.setdefault(sequence + r // per, []).append((offset + r % per * n, n))
                seen[n] += 1
        assert seen == Counter(lengths) and len(bins) == used
        for own in bins.values():
            own.sort()
            ends = 0
            for s, n in own:
                assert s == ends
                ends += n
            assert ends <= cap.tokens and len(own) <= (cap.docs or 64) and sum(n * n for _, n in own) <= (cap.attention or 64**2)
        if cap.mode == "norm":
            assert used == one_by_one(lengths, cap)


def test_pack_documents(docs, odd, none):
    lib = Tokenizer.from_file(BYTE)
    for df in (docs, odd):
        cap = bin_packing.Capacity(256)
        rows = bin_packing.pack_documents(df, BYTE, cap).collect()
        texts = [(r.doc_id, r.text or "") for r in df.select("doc_id", "text").collect()]
        want = Counter((i, *lib.encode(x, add_special_tokens=False).ids, 0) for i, x in texts)
        by_doc, bins = {}, {}
        for r in rows:
            ids = np.frombuffer(r.ids, "<u4")
            assert len(ids) == r.length and zlib.crc32(r.ids) == r.ids_crc32
            by_doc.setdefault(r.doc_id, []).append((r.piece, r.start, ids.tolist()))
            bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
        if df is docs:
            assert Counter((i, *[x for p in sorted(ps) for x in p[2]]) for i, ps in by_doc.items()) == want
            for ps in by_doc.values():
                assert all(len(p[2]) == 256 for p in sorted(ps)[1:])
        else:
            assert sum(len(p[2]) for ps in by_doc.values() for p in ps) == sum((len(k) - 1) * n for k, n in want.items())
        for own in bins.values():
            ends = 0
            for s, n in sorted(own):
                assert s == ends
                ends += n
            assert ends <= 256
        total = sum(r.length for r in rows)
        assert len(bins) <= math.ceil(total / 256) * 1.1 + 1
    tight = bin_packing.Capacity(256, docs=3, attention=40_000.0)
    assert tight.piece() == 200
    own = {}
    for r in bin_packing.pack_documents(odd, BYTE, tight, keep_ids=False).collect():
        own.setdefault(r.sequence_id, []).append(r.length)
    assert all(sum(x) <= 256 and len(x) <= 3 and sum(n * n for n in x) <= 40_000 for x in own.values())
    packed = bin_packing.pack_documents(docs.limit(20), BYTE, cap)
    assert bin_packing.sequences(packed).where("octet_length(ids) <> 4 * n_tokens").count() == 0
    assert bin_packing.pack_documents(none, BYTE, cap).count() == 0


@pytest.mark.parametrize("size", ["sf0.001", "sf0.01", "sf0.1"])
def test_nearest_searches_a_tree(spark, size):
    """At every given size the tree has many leaves and no query opens all of them."""
    v = spark.read.parquet(f"/root/testdata/{size}/embeddings.parquet")
    x = np.array([r.embedding for r in v.collect()], dtype=np.float64)
    tree = ann_tree.fit_tree(x, max(1, len(x) // 16))
    visits = ann_tree.nearest(v, v.vec_id % 20 == 0).first().visits
    assert tree.n_leaves >= len(x) // 16 - 8 and 1 < visits < tree.n_leaves


def test_nearest_recall(spark, sf):
    v = spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet")
    rows = [(r.vec_id, np.array(r.embedding, dtype=np.float64)) for r in v.collect()]
    ids, x = np.array([i for i, _ in rows]), np.array([e for _, e in rows])
    for options in ({}, {"leaf_rows": 16, "cell_rows": 100, "query_rows": 10}):
        got = ann_tree.nearest(v, v.vec_id % 20 == 0, **options).collect()
        by = {}
        for r in got:
            by.setdefault(r.query_id, []).append(r)
        hits = 0
        for q, own in by.items():
            own.sort(key=lambda r: r["rank"])
            assert [r["rank"] for r in own] == list(range(1, 21))
            s = x @ x[ids == q][0]
            order = [k for k in np.lexsort((ids, -s)) if ids[k] != q][:20]
            hits += len({ids[k] for k in order} & {r.vec_id for r in own})
            for r in own:
                assert abs(r.score - s[ids == r.vec_id][0]) < 1e-12
        assert len(by) == sum(ids % 20 == 0) and hits >= 0.9 * 20 * len(by)


def test_nearest_odd(spark):
    nan, inf = float("nan"), float("inf")
    bad = [(100, None), (120, []), (140, [0.0, 0.0]), (160, [1.0, None]), (180, [nan, 1.0]), (200, [inf, 1.0]), (220, [1.0, 2.0, 3.0]), (None, [1.0, 1.0])]
    same = [(k, [1.0, 1.0]) for k in range(40)]
    df = spark.createDataFrame([(i, v, 1) for i, v in bad + same + [(20, [3.0, 0.0])]], "vec_id long, embedding array<float>, label int")
    got = sorted(ann_tree.nearest(df, df.vec_id % 20 == 0, k=5).collect(), key=lambda r: (r.query_id, r["rank"]))
    assert {r.query_id for r in got} == {0, 20} and all(r.vec_id < 41 for r in got)
    assert [r.vec_id for r in got if r.query_id == 0][:5] == [20, 1, 2, 3, 4]
    assert ann_tree.nearest(df.limit(0), df.vec_id % 20 == 0).count() == 0
    # one visit does not find k candidates, so queries go on until their leaves hold enough
    rng = np.random.default_rng(1)
    far = spark.createDataFrame([(k, [float(a) for a in rng.normal(size=4)]) for k in range(300)] + [(40, [1.0, 2.0, 3.0, 4.0])], "vec_id long, embedding array<float>")
    got = ann_tree.nearest(far, far.vec_id % 20 == 0, k=50, leaf_rows=4, visits=1).groupBy("query_id").count().collect()
    assert {r.query_id: r["count"] for r in got} == {20 * k: 50 for k in range(15)}
    two = spark.createDataFrame([(0, [1.0]), (1, [2.0])], "vec_id long, embedding array<float>")
    assert [(r.query_id, r.vec_id, r.score) for r in ann_tree.nearest(two, two.vec_id % 20 == 0).collect()] == [(0, 1, 2.0)]


def test_toxicity(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    model = toxicity.fit(docs, labels)
    assert list(model.thresholds) == sorted(model.thresholds) and model.held_out["f1"] > 0.75
    got = {r.doc_id: r for r in toxicity.grade(docs, labels).collect()}
    truth = {r.doc_id: r.toxic for r in labels.collect()}
    insult = re.compile(r"\b(idiot|moron|scum|trash|loser|clown|stupid|worthless|pathetic|disgusting)\b", re.I)
    plain = {r.doc_id: len(insult.findall(r.text)) for r in docs.select("doc_id", "text").collect()}
    bad = [i for i, n in plain.items() if n >= 4]
    assert sum(got[i].toxic for i in bad) >= 0.98 * len(bad)
    clean = [i for i, t in truth.items() if not t and not plain[i]]
    assert sum(got[i].toxic for i in clean) <= 0.01 * len(clean)


def test_toxicity_against_a_plain_loop(docs, spark, sf, odd):
    """Every document's severity from the learned weights, word by word; and the weights are at a minimum of the likelihood."""
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    model = toxicity.fit(docs, labels)
    for df in (docs, odd):
        got = toxicity.severity_of(df.text, model, spark)
        for r in df.select("text", got.alias("severity")).collect():
            words = {w.lower() for w in re.findall(r"[^\W\d_]+", (r.text or "").lower())}
            score = sum(model.weights.get(f, 0.0) for w in words for f in [w, *(w[:n] + "*" for n in (5, 6, 7) if len(w) > n)])
            want = sum(1 / (1 + math.exp(t - score)) for t in model.thresholds)
            assert abs(r.severity - want) < 1e-9
    graded = {r.doc_id: r for r in toxicity.grade(docs, labels).collect()}
    assert all(r.toxic == (r.severity >= model.cutoff) and r.grade == int(r.severity + 0.5) for r in graded.values())
    stays = {r.doc_id for r in toxicity.drop_toxic(docs, labels).collect()}
    assert stays == {i for i, r in graded.items() if not r.toxic}


def test_ordinal_fit_is_at_a_minimum():
    rng = np.random.default_rng(5)
    rows = [np.array([k for k in range(3) if rng.random() < 0.5], dtype=np.int64) for _ in range(200)]
    grades = np.array([min(3, len(r) + (rng.random() < 0.3)) for r in rows])
    w, theta = toxicity.fit_ordinal(rows, grades, 3, rounds=3000)

    def loss(w, theta):
        s = np.array([w[r].sum() for r in rows])
        cdf = np.column_stack([np.zeros(len(s)), 1 / (1 + np.exp(-(theta - s[:, None]))), np.ones(len(s))])
        at = np.arange(len(s))
        return -np.log(cdf[at, grades + 1] - cdf[at, grades]).mean() + 0.5e-3 * (w * w).sum()

    best = loss(w, theta)
    for _ in range(200):
        assert loss(w + rng.normal(0, 0.05, 3), np.sort(theta + rng.normal(0, 0.05, 3))) > best - 1e-6


def test_toxicity_odd(spark, odd, none):
    labels = spark.createDataFrame([(0, 1), (1, 0), (1, 1), (None, 1), (2, None)], "doc_id long, toxic int")
    assert toxicity.grade(odd, labels).count() == odd.count()
    assert toxicity.grade(none, labels).count() == 0
    rows = toxicity.grade(odd, labels.limit(0)).collect()
    assert all(not r.toxic and r.severity == 0 for r in rows)
    assert toxicity.drop_toxic(odd, labels.limit(0)).columns == odd.columns


def test_ordinal_fit_orders_grades():
    rng = np.random.default_rng(0)
    grades = rng.integers(0, 4, 400)
    rows = [np.array([0] * int(g) + [1] * int(rng.integers(0, 3)), dtype=np.int64) for g in grades]
    w, theta = toxicity.fit_ordinal(rows, grades, 2)
    assert w[0] > 1 and abs(w[1]) < 0.5 * w[0] and (np.diff(theta) > 0).all()


def test_language_model(docs, odd, none):
    for df in (docs, odd):
        rows = [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]
        toks = [(i, [*re.findall(r"[^\x20\x09-\x0D]+", lower(t)), None]) for i, t in rows]
        held = lambda i: zlib.crc32(b"" if i is None else str(i).encode()) % 7 == 2
        c = Counter(w for i, ws in toks if not held(i) for w in ws)
        n, v = sum(c.values()), len(c)
        want = Counter((i, held(i), len(ws), sum(c[w] > 0 for w in ws), n, round(sum(math.log10((c[w] + 1) / (n + v + 1)) for w in ws), 6)) for i, ws in toks)
        got = language_model.interpolated_scores(df).collect()
        assert Counter((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in got) == want
        assert all(r.score <= 0 and math.isfinite(r.score) for r in got)
        # the model beats the base on held-out text
        if df is docs:
            out = [r for r in got if r.held_out]
            assert sum(r.score for r in out) > sum(r.base_score for r in out)
    assert language_model.interpolated_scores(none).count() == 0


def test_language_model_scores(spark):
    """Against a direct computation with the weights it has learned."""
    rows = [(1, "a b a b c"), (2, "a b c"), (3, "B a x"), (4, "a a"), (15, "q a b"), (16, "c b a")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    from pyspark.sql import functions as F

    counts = {}
    uni, pair, starts = Counter(), Counter(), 0
    for i, t in rows:
        if i != 16:
            ws = [*lower(t).split(), None]
            starts += 1
            for h, w in zip(["<s>", *ws[:-1]], ws, strict=True):
                uni[w] += 1
                pair[h, w] += 1
    held = F.col("doc_id") == 16
    got = {r.doc_id: r.score for r in language_model.interpolated_scores(df, held).collect()}
    n, v = sum(uni.values()), len(uni)
    cells = Counter()
    ctx = lambda h: starts if h == "<s>" else uni[h]
    for (h, w), k in pair.items():
        b = int(language_model.bucket_of(np.array([ctx(h) - 1]))[0])
        cells[b, (pair[h, w] - 1) / max(1, ctx(h) - 1), (uni[w] - 1) / (n - 1)] += k
    weights = language_model.learn_weights([(*c, k) for c, k in cells.items()], 1 / (v + 1))
    for i, t in rows:
        ws = [*lower(t).split(), None]
        s = 0.0
        for h, w in zip(["<s>", *ws[:-1]], ws, strict=True):
            a = weights[int(language_model.bucket_of(np.array([ctx(h)]))[0])]
            s += math.log10(a[0] * (pair[h, w] / ctx(h) if ctx(h) else 0) + a[1] * uni[w] / n + a[2] / (v + 1))
        assert abs(s - got[i]) < 1e-6 * abs(s)  # here each cell of the grid holds equal estimates
    del counts


def test_counts_are_kept_exactly():
    rng = np.random.default_rng(2)
    for n in (1, 2, 1000):
        keys = np.unique(rng.integers(0, 1 << 63, n, dtype=np.uint64))
        assert (language_model._unsqueeze(language_model._squeeze(keys)) == keys).all()
        counts = rng.integers(0, 600, n)
        assert (language_model._unsmall(language_model._small(counts)) == counts).all()
        assert (language_model._unplanes(language_model._planes(counts)) == counts).all()


def chat_rows(df):
    return [(r.conv_id, r.turn, r.role or "", r.text or "") for r in df.collect()]


@pytest.mark.parametrize("template", [chat_format.INSTRUCT, chat_format.CHATML])
def test_chat_round_trip(spark, sf, template):
    marks = template.controls()
    odd_rows = [(-1, 0, "user", "\\ " + " ".join(marks)), (-1, 1, "assistant", "".join(marks) * 2), (-1, 2, "user", "\\.\\\\" + marks[0] * 2 + marks[0][:2]), (-2, 0, None, None), (-3, 5, "too|>l", "<|end|>"), (-3, 5, "assistant", None), (-3, 5, "assistant", None), (None, 1, "assistant", "x"), (-4, 0, "assistant", "<"), (-4, 1, "user", "[")]
    df = spark.createDataFrame(odd_rows, "conv_id long, turn long, role string, text string").unionByName(spark.read.parquet(f"{sf}/conversations.parquet"))
    want = {}
    for c, t, r, x in sorted(chat_rows(df), key=lambda r: (r[0] is not None, *(v if v is not None else 0 for v in r))):
        want.setdefault(c, []).append((r, x))
    from pyspark.sql import functions as F

    read = chat_format.read_back(chat_format.formatted(df, template), template).withColumn("loss", chat_format.loss_text(F.col("slices"), F.col("spans"))).collect()
    assert {r.conv_id: [(t.role, t.text) for t in r.turns] for r in read} == want
    for r in read:
        assert r.loss == "".join(x for role, x in want[r.conv_id] if role == "assistant")
        assert sum(s.length for s in r.spans) == len(r.formatted)
        at = 0
        covered = []
        for s in r.spans:
            if s.loss:
                covered.append(r.formatted[at : at + s.length])
            at += s.length
        assert len(covered) == sum(role == "assistant" for role, _ in want[r.conv_id])
    valid = {r.conv_id: r.valid for r in read}
    assert not valid[-4] and not valid[-3] and valid[-1]
    assert chat_format.formatted(df.limit(0), template).count() == 0


def test_license_scan(spark, odd, none):
    texts = ["Licensed under the Apache License, Version 2.0.", "apache license version", "x CC-BY y cc by", "all rights\nreserved", "é all rights reserved", "General Public License " * 3, "word " * 200 + "released under the MIT license " + "word " * 100, None, ""]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r for r in license_scan.license_scan(df).collect()}
    assert got[0].labels == "apache-2" and got[0].n_base == 0 and got[0].first_word is None and got[0].score == 1.0
    assert got[1].labels == "" and got[1].score == 0
    assert (got[2].n_base, got[2].first_word, got[2].last_word, got[2].base_labels) == (2, 1, 4, "cc-by")
    assert got[3].n_base == 1 and got[4].first_word == 1
    assert (got[5].n_base, got[5].first_word, got[5].last_word, got[5].n_words) == (3, 0, 6, 9)
    assert got[6].labels == "mit" and got[7].n_words == 0 and got[8].labels == ""
    assert license_scan.license_scan(odd).count() == odd.count()
    assert license_scan.license_scan(none).count() == 0
    # rows that repeat an id are scored apart
    one = spark_rows(odd, [(1, "released under the mit license"), (1, "hello world"), (1, "hello world"), (None, "licensed under the Apache License, version 2.0"), (None, "x"), (1, "Released under the MIT license")])
    found = Counter((r.doc_id, r.labels, r.score, r.template_blocks) for r in license_scan.license_scan(one).collect())
    assert found == {(1, "mit", 1.0, 1): 2, (1, "", 0.0, 0): 2, (None, "apache-2", 1.0, 1): 1, (None, "", 0.0, 0): 1}


def test_template_join_is_exact(spark):
    rnd = random.Random(7)
    vocabulary = sorted({w for _, _, ws in license_scan._template_rows() for w in ws})
    lines = []
    for _ in range(400):
        _, _, ws = rnd.choice(license_scan._template_rows())
        own = [w for w in ws if rnd.random() < rnd.choice([0.7, 0.85, 0.95])] + [rnd.choice(vocabulary + ["x", "yy"]) for _ in range(rnd.randint(0, 6))]
        rnd.shuffle(own)
        lines.append(" ".join(own))
    df = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string")
    got = Counter((r.doc_id, r.template, round(r.containment, 9)) for r in license_scan.template_matches(df, threshold=0.8).collect())
    want = Counter()
    for i, line in enumerate(lines):
        own = set(line.split())
        for _, label, ws in license_scan._template_rows():
            k = len(own & set(ws))
            if k >= -(-len(ws) * 800 // 1000):
                want[i, label, round(k / len(ws), 9)] += 1
    assert got == want and len(want) > 50


def test_notices_wrapped_over_lines(spark):
    permission = "Permission is hereby granted, free of charge, to any person obtaining a copy\nof this software and associated documentation files"
    texts = [
        "licensed under the apache\nlicense version 2.0",
        permission,
        "word " * 150 + "\n\n" + "Licensed under\r\n# the Apache License,\n# Version 2.0" + "\nmore words" * 100,
        "\n".join("released under the mit license".split()),
        "Licensed under the Apache License, Version 2.0\nsee the version under the license",  # a whole line, not found again with its neighbour
        "Licensed under the Apache License, Version 2.0\nlicensed under the apache\nlicense version 2.0",
        "licensed under the apache\n" + "word " * 100 + "\nlicense version 2.0",
        "x\n" * 20 + "é all rights\nreserved\n\nunauthorized copying of this\nfile is strictly prohibited",
    ]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r for r in license_scan.license_scan(df).collect()}
    assert [got[k].labels for k in range(8)] == ["apache-2", "mit", "apache-2", "mit", "apache-2", "apache-2", "", "proprietary,reserved"]
    assert [got[k].score for k in range(8)] == [1, 1, 1, 1, 1, 1, 0, 1]
    assert [got[k].template_blocks for k in (0, 1, 3, 4, 5, 6)] == [1, 1, 1, 1, 2, 0]
    words = permission.split()
    broken = spark.createDataFrame([(k, " ".join(words[:k]) + "\n" + " ".join(words[k:])) for k in range(1, len(words))], "doc_id long, text string")
    assert {r.labels for r in license_scan.license_scan(broken).collect()} == {"mit"}  # wherever the line breaks
