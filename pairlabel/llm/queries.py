"""The queries of this subpackage, each over its whole table, and the SQL that gives the same rows where SQL can."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann_tree, bin_packing, bit_packing, bpe, chat_format, exact_dedup, language_model, license_scan, near_duplicates, toxicity
from .common import documents


def op1_kmeans_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann_tree.nearest(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), F.col("vec_id") % 20 == 0)


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    packed = bin_packing.pack_documents(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"), keep_ids=False)
    return packed.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def op3_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.license_scan(documents(spark, sf_dir))


def op4_bit_packed_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    blocks = bit_packing.pack_corpus(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"), end_id=2)
    return bit_packing.read_documents(blocks).select("doc_id", "start", "n_tokens", bit_packing.crc32_of("ids").alias("ids_crc32"))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.grade(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op6_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = "</s>[INST] ok [/INST]"
    more = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text").unionByName(more)
    read = chat_format.read_back(chat_format.formatted(turns))
    told = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = chat_format.loss_text(F.col("slices"), F.col("spans"))
    return read.withColumn("loss_text", loss).select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(told, 256).alias("turns_sha256"),
        F.length("loss_text").cast("long").alias("loss_chars"),
        F.sha2("loss_text", 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
        "valid",
        "complete",
    )


def op7_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(documents(spark, sf_dir))


def op8_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"))


def op9_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates.jaccard_components(documents(spark, sf_dir)).select("doc_id", "n_shingles", "component_id")


def op10_deleted_interpolation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_model.interpolated_scores(documents(spark, sf_dir))


QUERIES = {
    f.__name__: f
    for f in (
        op1_kmeans_tree, op2_best_fit_packing, op3_license_scan, op4_bit_packed_ids, op5_toxicity, op6_chat_formatting,
        op7_exact_dedup, op8_bpe_round_trip, op9_ngram_jaccard, op10_deleted_interpolation,
    )
}

_LOWERED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

_OP7 = f"""
WITH d AS (SELECT doc_id, {_LOWERED} AS norm FROM documents),
     g AS (SELECT norm, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY norm)
SELECT d.doc_id, g.keep_id, g.group_size, d.doc_id IS NOT DISTINCT FROM g.keep_id AS kept, sha256(d.norm) AS text_sha256
FROM d JOIN g ON d.norm = g.norm"""


def _sql_text(s: str) -> str:
    return "'" + s.replace("'", "''") + "'"


def _op6_sql() -> str:
    t = chat_format.INSTRUCT
    a, b, c = t.other
    esc = "replace({}, '\\', '\\\\')"
    broken = "s"
    for mark in t.controls():
        broken = f"replace({broken}, {_sql_text(mark)}, {_sql_text(mark[0] + chr(1) + mark[1:])})"
    broken = f"replace({broken}, chr(1), '\\.')"
    size = lambda x: f"length({broken.replace('(s,', '(' + esc.format(x) + ',', 1)})"
    marks = "CASE role " + " ".join(f"WHEN '{r}' THEN {len(t.before[r]) + len(t.after[r])}" for r in t.before) + f" ELSE {len(a) + len(b) + len(c)} + {size('role')} END"
    steps = " OR ".join(f"(last IS NULL AND role = '{y}')" if x is None else f"(last = '{x}' AND role = '{y}')" for x, y in t.steps)
    return f"""
WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
           UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
     o AS (SELECT *, lag(role) OVER w AS last, lead(role) OVER w AS next FROM c WINDOW w AS (PARTITION BY conv_id ORDER BY turn, role, text))
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
       CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
       CAST(sum({marks} + {size('text')}) AS BIGINT) AS formatted_chars,
       bool_and(coalesce({steps}, false)) AS valid, bool_or(next IS NULL AND role = 'assistant') AS complete
FROM o GROUP BY conv_id"""


def _op3_sql(threshold: float = 0.85, window: int = 64) -> str:
    sep = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
    words = "list_filter(regexp_split_to_array({}, '" + sep + "'), lambda x: x <> '')"
    places = []
    for p, label in license_scan.PHRASES.items():
        ws = p.split()
        cond = " AND ".join(f"w[i + {k}] = '{x}'" for k, x in enumerate(ws))
        places.append(f"list_transform(list_filter(range(1, len(w) - {len(ws) - 2}), lambda i: {cond}), lambda i: {{'at': i - 1, 'label': '{label}'}})")
    templates = ", ".join(
        f"('{label}', [{', '.join(_sql_text(x) for x in ws)}], {-(-len(ws) * int(round(threshold * 1000)) // 1000)})" for _, label, ws in license_scan._template_rows()
    )
    half = window // 2
    return f"""
WITH d AS (SELECT doc_id, {_LOWERED} AS norm FROM documents),
     b AS (SELECT doc_id, {words.format('norm')} AS w FROM d),
     p AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, list_concat({places[0]}, list_concat({places[1]}, {places[2]})) AS places FROM b),
     l AS (SELECT doc_id, {words.format('line')} AS lw FROM (SELECT doc_id, unnest(string_split(norm, chr(10))) AS line FROM d)),
     blocks AS (SELECT doc_id, list_distinct(list_slice(lw, i + 1, i + {window})) AS bw
                FROM (SELECT doc_id, lw, unnest(CASE WHEN len(lw) <= {window} THEN [0] ELSE range(0, len(lw), {half}) END) AS i FROM l WHERE len(lw) > 0)),
     t(label, tw, need) AS (VALUES {templates}),
     m AS (SELECT doc_id, label, len(list_intersect(bw, tw)) / len(tw) AS containment FROM blocks, t WHERE len(list_intersect(bw, tw)) >= need),
     f AS (SELECT doc_id, list(DISTINCT label) AS found, max(containment) AS containment, count(*) AS n FROM m GROUP BY doc_id)
SELECT p.doc_id, n_words, CAST(len(places) AS BIGINT) AS n_base,
       CAST(list_min(list_transform(places, lambda x: x.at)) AS BIGINT) AS first_word, CAST(list_max(list_transform(places, lambda x: x.at)) AS BIGINT) AS last_word,
       array_to_string(list_sort(list_distinct(list_transform(places, lambda x: x.label))), ',') AS base_labels,
       array_to_string(list_sort(list_distinct(list_concat(list_transform(places, lambda x: x.label), coalesce(found, [])))), ',') AS labels,
       CAST(CASE WHEN len(places) > 0 THEN 1.0 ELSE coalesce(containment, 0) END AS DOUBLE) AS score, CAST(coalesce(n, 0) AS BIGINT) AS template_blocks
FROM p LEFT JOIN f ON p.doc_id = f.doc_id"""


ORACLE_SQL = {"op3_license_scan": _op3_sql(), "op6_chat_formatting": _op6_sql(), "op7_exact_dedup": _OP7}
