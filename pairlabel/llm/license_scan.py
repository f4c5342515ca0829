"""License scans: phrase places by word position, and an exact set-similarity join with license templates; DataFrame functions only.

The join finds every block of a text that holds at least ``threshold`` of a
template's distinct words. Template words are put in one global order, rarest
first, by the number of documents that hold them (counted over all documents).
A block can only qualify if it holds one of the template's first
``size - need + 1`` words (prefix filter), holds at least ``need`` template words
(length filter), and if the words that follow the shared one in both suffice
(positional filter); what is left is counted exactly.

A block is a line, or, in lines longer than ``window`` words, each window of so
many words that starts at a multiple of half of it. Notices wrapped over lines are
met by the same windows over the words of the whole text: such a window is a block
if it spans lines, and the words of lines that hold the template by themselves do
not count in it, so a notice within a line is not found again from beside it.

Defined results: null text counts as empty and gives zero counts, null places and
empty label strings; rows that repeat an id are scored apart, each by its own text
(matches are joined by id and digest of the text), and so are rows with a null id;
templates and phrases are fixed values, so what is broadcast has a fixed size; an empty table
gives an empty result; columns other than the two named ones play no part.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower

#: Phrases whose places are counted, and their labels.
PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: Short license notices, as words.
TEMPLATES = {
    "mit": ["released under the mit license", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"],
    "apache-2": ["licensed under the apache license version 2 0"],
    "gpl-notice": ["this work is licensed under the gnu general public license version 3", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license"],
    "cc-by-nc": ["licensed under cc by nc 4 0"],
    "cc-by-sa": ["licensed under cc by sa 4 0", "this work is licensed under a creative commons attribution sharealike license"],
    "bsd": ["redistribution and use in source and binary forms with or without modification are permitted"],
    "mpl": ["this source code form is subject to the terms of the mozilla public license v 2 0"],
    "public-domain": ["this work is released into the public domain", "dedicated to the public domain under cc0"],
    "proprietary": ["all rights reserved unauthorized copying of this file is strictly prohibited"],
}
_SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words_line(lowered: Column) -> Column:
    """The words, one space apart."""
    return F.trim(F.regexp_replace(lowered, _SEPARATORS, " "))


def _word_count(line: Column) -> Column:
    return F.when(line == "", F.lit(0)).otherwise(F.length(line) - F.length(F.replace(line, F.lit(" "), F.lit(""))) + 1).cast("bigint")


def _template_rows() -> list[tuple[int, str, list[str]]]:
    return [(k, label, sorted(set(text.split()))) for k, (label, text) in enumerate((lab, t) for lab, ts in TEMPLATES.items() for t in ts)]


def phrase_places(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", phrases: dict[str, str] = PHRASES) -> DataFrame:
    """doc_id, text_key (digest of the lowered text), n_words, n_base, first_word, last_word, base (array of labels), per row of docs."""
    rows = docs.select(F.col(id_col).alias("doc_id"), ascii_lower(F.col(text_col)).alias("text"))
    rows = rows.select("doc_id", F.sha2("text", 256).alias("text_key"), words_line(F.col("text")).alias("line")).withColumn("n_words", _word_count(F.col("line")))
    padded = F.concat(F.lit(" "), F.col("line"), F.lit(" "))
    any_phrase = None
    for p in phrases:
        has = padded.contains(f" {p} ")
        any_phrase = has if any_phrase is None else any_phrase | has
    w = F.split("line", " ")

    def stands(i: Column, phrase: str) -> Column:
        out = None
        for k, word in enumerate(phrase.split()):
            same = F.get(F.col("w"), i + k) == word
            out = same if out is None else out & same
        return F.coalesce(out, F.lit(False))

    def label_at(i: Column) -> Column:
        out = F.lit(None).cast("string")
        for p, label in phrases.items():
            out = F.when(stands(i, p), F.lit(label)).otherwise(out)
        return out

    # only texts that hold a phrase are split
    rows = rows.withColumn("w", F.when(any_phrase, w).otherwise(F.array().cast("array<string>")))
    firsts = [p.split()[0] for p in phrases]
    at = F.transform(F.col("w"), lambda x, i: F.when(x.isin(*firsts), F.struct(i.cast("bigint").alias("at"), label_at(i).alias("label"))))
    rows = rows.withColumn("places", F.filter(at, lambda x: x["label"].isNotNull()))
    return rows.select(
        "doc_id",
        "text_key",
        "n_words",
        F.size("places").cast("bigint").alias("n_base"),
        F.array_min(F.col("places.at")).alias("first_word"),
        F.array_max(F.col("places.at")).alias("last_word"),
        F.array_sort(F.array_distinct(F.col("places.label"))).alias("base"),
    )


def word_order(docs: DataFrame, text_col: str = "text") -> dict[str, int]:
    """Template words, rarest first, by the number of all documents that hold them. Its size is that of the templates."""
    vocabulary = sorted({w for _, _, ws in _template_rows() for w in ws})
    line = words_line(ascii_lower(F.col(text_col)))
    held = F.array_intersect(F.split(line, " "), F.array(*map(F.lit, vocabulary)))
    counts = docs.select(F.explode(held).alias("word")).groupBy("word").count().collect()
    df = {r["word"]: r["count"] for r in counts}
    return {w: k for k, w in enumerate(sorted(vocabulary, key=lambda w: (df.get(w, 0), w)))}


def template_matches(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.85, window: int = 64) -> DataFrame:
    """One row per distinct text of an id, qualifying block and template: doc_id, text_key, block (line, or -1 if it spans lines, and window), template (label), containment."""
    spark = docs.sparkSession
    order = word_order(docs, text_col)
    templates, prefix = [], []
    for k, label, ws in _template_rows():
        ranked = sorted(order[w] for w in ws)
        need = -(-len(ranked) * int(round(threshold * 1000)) // 1000)
        templates.append((k, label, ranked, need, len(ranked)))
        prefix += [(r, k, i, need, len(ranked)) for i, r in enumerate(ranked[: len(ranked) - need + 1])]
    t = spark.createDataFrame(templates, "template_id int, template string, t_words array<int>, t_need int, t_size int")
    p = spark.createDataFrame(prefix, "rank int, template_id int, t_at int, need int, size int")
    least = min(x[3] for x in templates)

    starters = sorted({w for w, r in order.items() if any(r == x[0] for x in prefix)})
    rows = docs.select(F.col(id_col).alias("doc_id"), ascii_lower(F.col(text_col)).alias("text"))
    rows = rows.where(words_line(F.col("text")).rlike(r"(^| )(" + "|".join(starters) + r")( |$)"))
    ranks = F.create_map(*[x for word, r in order.items() for x in (F.lit(word), F.lit(r))])
    vocabulary = F.array(*[F.lit(x) for x in order])
    half = window // 2
    starts = lambda w: F.sequence(F.lit(0), F.greatest(F.size(w) - 1, F.lit(0)), F.lit(half))
    entry = lambda n, word: F.struct(n.alias("line"), F.element_at(ranks, word).alias("rank"))

    def of_line(w: Column, n: Column) -> Column:
        at = F.when(F.size(w) <= window, F.array(F.lit(0))).otherwise(starts(w))
        return F.transform(at, lambda i, part: F.struct(n.alias("line_no"), part.alias("part"), F.transform(F.array_intersect(F.slice(w, i + 1, F.lit(window)), vocabulary), lambda x: entry(n, x)).alias("entries")))

    def across(seq: Column) -> Column:
        spans = F.filter(starts(seq), lambda i: F.get(seq, i)["line"] != F.get(seq, F.least(i + window, F.size(seq)) - 1)["line"])
        held = lambda i: F.filter(F.slice(seq, i + 1, F.lit(window)), lambda x: x["word"].isin(*order))
        return F.transform(spans, lambda i: F.struct(F.lit(-1).alias("line_no"), (i / half).cast("int").alias("part"), F.transform(held(i), lambda x: entry(x["line"], x["word"])).alias("entries")))

    rows = rows.select("doc_id", F.sha2("text", 256).alias("text_key"), F.transform(F.split("text", "\n"), lambda x: F.split(words_line(x), " ")).alias("lines"))
    seq = F.flatten(F.transform("lines", lambda w, n: F.transform(F.filter(w, lambda x: x != ""), lambda x: F.struct(n.alias("line"), x.alias("word")))))
    rows = rows.withColumn("seq", seq)  # inline_outer below: for inline, Spark would test the size of blocks under the projections and build seq anew for each window
    rows = rows.select("doc_id", "text_key", F.concat(F.flatten(F.transform("lines", of_line)), across(F.col("seq"))).alias("blocks"))
    blocks = rows.select("doc_id", "text_key", F.inline_outer("blocks")).withColumn("b_words", F.array_sort(F.array_distinct("entries.rank"))).where(F.size("b_words") >= least)  # length filter
    entries = blocks.select("*", F.posexplode("b_words").alias("b_at", "rank"))
    joined = entries.join(F.broadcast(p), "rank").where(
        (F.size("b_words") >= F.col("need"))
        # the shared word is the first of both or follows at most b_at and t_at shared ones
        & (F.least(F.col("b_at"), F.col("t_at")) + F.least(F.size("b_words") - F.col("b_at"), F.col("size") - F.col("t_at")) >= F.col("need"))
    )
    shared = lambda es: F.size(F.array_intersect(F.transform(es, lambda e: e["rank"]), F.col("t_words")))
    joined = joined.join(F.broadcast(t), "template_id").where(F.size(F.array_intersect("b_words", "t_words")) >= F.col("t_need"))
    # the blocks of one text that hold a template, each once
    pairs = joined.groupBy("doc_id", "text_key", "template_id").agg(F.collect_set(F.struct("line_no", "part", "entries")).alias("blocks")).join(F.broadcast(t), "template_id")
    whole = F.filter("blocks", lambda x: x["line_no"] >= 0)
    pairs = pairs.withColumn("own_lines", F.array_distinct(F.transform(whole, lambda x: x["line_no"])))
    counted = F.transform("blocks", lambda x: F.struct(
        x["line_no"].alias("line_no"), x["part"].alias("part"),
        shared(F.when(x["line_no"] >= 0, x["entries"]).otherwise(F.filter(x["entries"], lambda e: ~F.array_contains("own_lines", e["line"])))).alias("shared"),
    ))
    found = pairs.select("doc_id", "text_key", "template", "t_need", "t_size", F.inline(counted))
    return found.where(F.col("shared") >= F.col("t_need")).select(
        "doc_id", "text_key", F.struct("line_no", "part").alias("block"), "template", (F.col("shared") / F.col("t_size")).alias("containment")
    )


def license_scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.85) -> DataFrame:
    """One row per document: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, template_blocks."""
    base = phrase_places(docs, id_col, text_col)
    found = (
        template_matches(docs, id_col, text_col, threshold)
        .groupBy(F.col("doc_id").alias("m_id"), F.col("text_key").alias("m_key"))
        .agg(F.collect_set("template").alias("found"), F.max("containment").alias("containment"), F.count(F.lit(1)).alias("template_blocks"))
    )
    out = base.join(found, F.col("doc_id").eqNullSafe(F.col("m_id")) & (F.col("text_key") == F.col("m_key")), "left")
    none = F.array().cast("array<string>")
    labels = F.array_sort(F.array_distinct(F.concat(F.col("base"), F.coalesce("found", none))))
    score = F.when(F.col("n_base") > 0, F.lit(1.0)).otherwise(F.coalesce("containment", F.lit(0.0)))
    return out.select(
        "doc_id", "n_words", "n_base", "first_word", "last_word",
        F.concat_ws(",", "base").alias("base_labels"), F.concat_ws(",", labels).alias("labels"),
        score.alias("score"), F.coalesce("template_blocks", F.lit(0)).cast("bigint").alias("template_blocks"),
    )
