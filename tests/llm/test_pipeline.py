
import corpus_pipeline
from pairlabel.llm import toxicity
from test_llm import brute_components, lower


def test_pipeline_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    bad = {r.doc_id for r in toxicity.grade(docs, labels).collect() if r.toxic}
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect() if r.doc_id not in bad]
    last = {}
    for i, t in sorted(rows):
        last[lower(t)] = (i, t)
    rows = sorted(last.values())
    comp = brute_components(rows)
    want = {i for i, c in comp.items() if i == c}
    got = corpus_pipeline.run(spark, sf).collect()
    assert {r.doc_id for r in got} == want
    bins = {}
    for r in got:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for own in bins.values():
        ends = 0
        for s, n in sorted(own):
            assert s == ends
            ends += n
        assert ends <= 2048


def test_stages_keep_columns_and_take_odd_rows(spark, sf):
    rows = [(None, None, None, None, None), (1, "", "en", "s", 0), (1, "", "en", "s", 0), (2, "a b c d e f g " * 9000, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in corpus_pipeline.STAGES:
        for df in (docs, docs.limit(0)):
            out = stage(spark, df, sf)
            got = out.collect()
            if name != corpus_pipeline.STAGES[-1][0]:
                assert out.columns == docs.columns
            if name == "exact_dedup" and df is docs:  # null and empty are one text, of which one row stays
                assert sorted(r.doc_id for r in got) == [1, 2]


def test_repeated_rows_through_all_stages(spark, sf):
    """Rows that repeat ids and texts: each stage against plain Python on what the one before has left."""
    base = [(k, " ".join(f"w{(k * 7 + j * j) % 97}" for j in range(40)), "en", "s", 9) for k in range(20)]
    near = [(100 + k, t + " more", "en", "s", 9) for k, t, *_ in base[:5]]
    rows = base + base[:3] + near + near[:2] + [(200, base[7][1].upper(), None, None, None), (3, base[9][1], None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    stages = dict(corpus_pipeline.STAGES)
    kept = stages["toxicity"](spark, docs, sf)
    bad = {r.text for r in toxicity.grade(docs, spark.read.parquet(f"{sf}/labels.parquet")).join(docs, "doc_id").where("toxic").collect()}
    assert sorted((r.doc_id, r.text) for r in kept.collect()) == sorted((i, t) for i, t, *_ in rows if t not in bad)
    last = {}
    for r in kept.collect():
        last[lower(r.text)] = max(last.get(lower(r.text), -1), r.doc_id)
    once = stages["exact_dedup"](spark, kept, sf)
    assert sorted((lower(r.text), r.doc_id) for r in once.collect()) == sorted(last.items())
    left = [(r.doc_id, r.text) for r in once.collect()]
    comp = brute_components(left)
    apart = stages["ngram_jaccard"](spark, once, sf)
    assert sorted(r.doc_id for r in apart.collect()) == sorted(i for i, _ in left if comp[i] == i)
    packed = stages["best_fit_packing"](spark, apart, sf).collect()
    assert sorted({r.doc_id for r in packed}) == sorted({r.doc_id for r in apart.collect()})
