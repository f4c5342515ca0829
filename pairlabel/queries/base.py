"""Shared pieces of the queries: tables that many of them use, and the same tables in SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines as B
from ..operators import easy as E
from ..operators import features as X
from ..operators import workload as W

_kept: dict[tuple, DataFrame] = {}


def kept(spark: SparkSession, sf_dir: str, name: str, make: Callable[[], DataFrame]) -> DataFrame:
    """A table that several queries of one session share is computed once; on a cluster write it instead."""
    key = (spark.sparkContext.applicationId, id(spark), sf_dir, name)
    if key not in _kept:
        _kept[key] = make().persist()
    return _kept[key]


def left(spark: SparkSession, d: str) -> DataFrame:
    """Not kept: words and bodies are several times the input, and batches of them fill the memory that kept pairs need; readers prune the columns."""
    return W.document_records(W.load(spark, d, "documents"))


def right(spark: SparkSession, d: str) -> DataFrame:
    return W.corrupt(left(spark, d))


def records(spark: SparkSession, d: str) -> DataFrame:
    return left(spark, d).unionByName(right(spark, d))


def blocked(spark: SparkSession, d: str) -> DataFrame:
    return kept(spark, d, "blocked", lambda: W.block_by_tokens(left(spark, d), right(spark, d)))


def pairs(spark: SparkSession, d: str) -> DataFrame:
    """W1h: documents against the dirty twin."""
    a, b = left(spark, d), right(spark, d)
    return kept(spark, d, "pairs", lambda: W.with_similarity(W.compare(blocked(spark, d), a, b), W.attribute_weights(a, b)))


def strict_truth(spark: SparkSession, d: str) -> DataFrame:
    return kept(spark, d, "strict", lambda: W.truth(pairs(spark, d), W.strict_entities(left(spark, d))))


def cluster_truth(spark: SparkSession, d: str) -> DataFrame:
    return kept(spark, d, "cluster", lambda: W.truth(pairs(spark, d), W.cluster_entities(left(spark, d))))


def rule_labels(spark: SparkSession, d: str) -> DataFrame:
    """Labels at a fixed cut, for the measures."""
    return pairs(spark, d).select("pair_id", (F.col("sim") >= 0.5).cast("int").alias("label"))


LO, HI = 0.25, 0.6


def easy(spark: SparkSession, d: str) -> DataFrame:
    return kept(spark, d, "easy", lambda: E.easy_by_bounds(pairs(spark, d), LO, HI))


def with_bodies(spark: SparkSession, d: str) -> DataFrame:
    return W.with_bodies(pairs(spark, d), left(spark, d), right(spark, d))


def incidence(spark: SparkSession, d: str) -> DataFrame:
    return kept(spark, d, "incidence", lambda: X.incidence(pairs(spark, d), records(spark, d)))


def share(spark: SparkSession, d: str) -> float:
    return B.match_share(pairs(spark, d))


# the same in SQL

TOKENS = r"list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '')"

RECORDS = rf"""
texts AS MATERIALIZED (SELECT doc_id AS rec_id, {TOKENS} AS words, source, CAST(n_chars AS DOUBLE) AS n_chars FROM documents),
l AS MATERIALIZED (SELECT rec_id, words[1:12] AS title, words[13:] AS body, source, n_chars, words FROM texts),
dirty AS (SELECT *, list_transform(range(0, len(words)), lambda i:
    CASE WHEN (rec_id * 7919 + i * 104729 + rec_id * i * 31) % 100 < 5 + (rec_id * 31) % 60 THEN NULL
         WHEN (rec_id * 13 + i * 17) % 10 = 0 AND length(words[i + 1]) > 3 THEN words[i + 1][1:1] || words[i + 1][3:]
         ELSE words[i + 1] END) AS k FROM texts),
r AS MATERIALIZED (SELECT rec_id, list_filter(k[1:12], lambda x: x IS NOT NULL) AS title, list_filter(k[13:], lambda x: x IS NOT NULL) AS body,
    CASE WHEN rec_id % 4 = 0 THEN 'src' || (rec_id % 20) ELSE source END AS source, n_chars * (1 + (rec_id % 7 - 3) / 50.0) AS n_chars,
    list_filter(k, lambda x: x IS NOT NULL) AS words FROM dirty),
records AS (SELECT * FROM l UNION ALL SELECT * FROM r)"""

BLOCKED = """
lt AS (SELECT rec_id, unnest(list_distinct(title)) AS token FROM l),
rt AS (SELECT rec_id, unnest(list_distinct(title)) AS token FROM r),
dfs AS (SELECT token, count(*) AS df FROM (SELECT token FROM lt UNION ALL SELECT token FROM rt) GROUP BY token),
blocked AS MATERIALIZED (SELECT lt.rec_id AS id_a, rt.rec_id AS id_b, count(*) AS shared FROM lt JOIN dfs USING (token) JOIN rt USING (token) WHERE df <= 200 GROUP BY 1, 2 HAVING count(*) >= 2)"""


def jaccard_sql(a: str, b: str) -> str:
    both = f"len(list_intersect({a}, {b}))"
    return f"coalesce({both} / nullif(CAST(len(list_distinct(list_concat({a}, {b}))) AS DOUBLE), 0), 0.0)"


_NUM = "CASE WHEN x.n_chars IS NULL OR y.n_chars IS NULL THEN 0.0 WHEN x.n_chars = y.n_chars THEN 1.0 ELSE greatest(0.0, 1 - coalesce(abs(x.n_chars - y.n_chars) / nullif(greatest(abs(x.n_chars), abs(y.n_chars)), 0), 0.0)) END"

COMPARED = f"""
compared AS MATERIALIZED (SELECT id_a * 2147483648 + id_b AS pair_id, id_a, id_b, {jaccard_sql('x.title', 'y.title')} AS sim_title, {jaccard_sql('x.body', 'y.body')} AS sim_body,
    CASE WHEN x.source IS NULL OR y.source IS NULL THEN 0.0 WHEN x.source = y.source THEN 1.0 ELSE 0.0 END AS sim_source, {_NUM} AS sim_num,
    x.title AS title_a, y.title AS title_b
    FROM blocked JOIN l x ON x.rec_id = id_a JOIN r y ON y.rec_id = id_b),
weights AS (SELECT count(DISTINCT title) AS wt, count(DISTINCT body) AS wb, count(DISTINCT source) AS ws, count(DISTINCT n_chars) AS wn FROM records),
pairs AS MATERIALIZED (SELECT compared.*, round(sim_title * (wt / CAST(wt + wb + ws + wn AS DOUBLE)) + sim_body * (wb / CAST(wt + wb + ws + wn AS DOUBLE))
    + sim_source * (ws / CAST(wt + wb + ws + wn AS DOUBLE)) + sim_num * (wn / CAST(wt + wb + ws + wn AS DOUBLE)), 9) AS sim FROM compared, weights)"""

PAIRS = f"WITH {RECORDS}, {BLOCKED}, {COMPARED}"

STRICT = """
named AS (SELECT rec_id, array_to_string(words, ' ') AS k FROM l),
entities AS (SELECT rec_id, min(rec_id) OVER (PARTITION BY k) AS entity_id FROM named),
truth AS MATERIALIZED (SELECT pair_id, CAST(ea.entity_id = eb.entity_id AS INT) AS truth FROM pairs JOIN entities ea ON ea.rec_id = id_a JOIN entities eb ON eb.rec_id = id_b)"""

LABELS = "labels_ AS (SELECT pair_id, CAST(sim >= 0.5 AS INT) AS label FROM pairs)"
EASY = f"easy AS MATERIALIZED (SELECT pair_id, CASE WHEN sim >= {HI} THEN 1 ELSE 0 END AS label FROM pairs WHERE sim >= {HI} OR sim <= {LO})"

BODIES = "WITH_BODIES AS (SELECT pairs.*, x.body AS body_a, y.body AS body_b FROM pairs JOIN l x ON x.rec_id = id_a JOIN r y ON y.rec_id = id_b)"


def lcs_sql(attr: str = "title", table: str = "pairs") -> str:
    """Longest common run by positions: equal tokens on one diagonal, numbered without gaps."""
    return f"""
ta AS (SELECT pair_id, unnest({attr}_a) AS t, generate_subscripts({attr}_a, 1) AS i FROM {table}),
tb AS (SELECT pair_id, unnest({attr}_b) AS t, generate_subscripts({attr}_b, 1) AS j FROM {table}),
meets AS (SELECT ta.pair_id, i - j AS diag, i, i - row_number() OVER (PARTITION BY ta.pair_id, i - j ORDER BY i) AS island FROM ta JOIN tb ON ta.pair_id = tb.pair_id AND ta.t = tb.t),
lcs AS MATERIALIZED (SELECT pair_id, max(n) AS run FROM (SELECT pair_id, diag, island, count(*) AS n FROM meets GROUP BY 1, 2, 3) GROUP BY pair_id)"""


LCS = lcs_sql()

FEATURE_ID = "CAST(('0x' || substr(md5(family || '|' || attr || '|' || token), 1, 15)) AS BIGINT)"

INCIDENCE = f"""
{LCS},
shares AS (SELECT pair_id, coalesce(run / nullif(CAST(least(len(title_a), len(title_b)) AS DOUBLE), 0), 0.0) AS x FROM pairs LEFT JOIN lcs USING (pair_id)),
idf AS (SELECT token, count(*) AS df, ln((SELECT count(*) FROM records) / CAST(count(*) AS DOUBLE)) AS idf FROM (SELECT unnest(list_distinct(title)) AS token FROM records) GROUP BY token),
rare AS (SELECT token FROM idf WHERE idf >= 3.0 AND df >= 2),
tall AS (SELECT pair_id, 'attr' AS family, 'sim_title' AS attr, '' AS token, sim_title AS x FROM pairs UNION ALL SELECT pair_id, 'attr', 'sim_body', '', sim_body FROM pairs
    UNION ALL SELECT pair_id, 'attr', 'sim_source', '', sim_source FROM pairs UNION ALL SELECT pair_id, 'attr', 'sim_num', '', sim_num FROM pairs
    UNION ALL SELECT pair_id, 'lcs', 'title', '', coalesce(x, 0.0) FROM shares
    UNION ALL SELECT pair_id, 'same', 'title', token, sim FROM (SELECT pair_id, sim, unnest(list_intersect(title_a, title_b)) AS token FROM pairs) SEMI JOIN rare USING (token)
    UNION ALL SELECT pair_id, 'diff', 'title', token, sim FROM (SELECT pair_id, sim, unnest(list_distinct(list_concat(list_filter(title_a, lambda x: NOT list_contains(title_b, x)), list_filter(title_b, lambda x: NOT list_contains(title_a, x))))) AS token FROM pairs) SEMI JOIN rare USING (token)),
incidence AS MATERIALIZED (SELECT pair_id, {FEATURE_ID} AS feature_id, family, attr, token, x FROM tall)"""

LOGIT = "4.59511985013459"
STATS = """
stats AS MATERIALIZED (SELECT feature_id, count(*) FILTER (WHERE label = 0) AS n0, coalesce(sum(x) FILTER (WHERE label = 0), 0.0) AS s0, coalesce(sum(x * x) FILTER (WHERE label = 0), 0.0) AS q0,
    count(*) FILTER (WHERE label = 1) AS n1, coalesce(sum(x) FILTER (WHERE label = 1), 0.0) AS s1, coalesce(sum(x * x) FILTER (WHERE label = 1), 0.0) AS q1
    FROM incidence JOIN easy USING (pair_id) GROUP BY feature_id),
weight AS (SELECT coalesce(count(*) FILTER (WHERE label = 0) / nullif(CAST(count(*) FILTER (WHERE label = 1) AS DOUBLE), 0), 1.0) AS w FROM easy)"""

CURVES = f"""
sums AS (SELECT feature_id, n0, s0, q0, n1, s1, q1, w, n0 + w * n1 AS sw, s0 + w * s1 AS sx, q0 + w * q1 AS sxx, (w * n1 - n0) * {LOGIT} AS sy, (w * s1 - s0) * {LOGIT} AS sxy, CAST(n0 + n1 AS DOUBLE) AS nobs FROM stats, weight),
slopes AS (SELECT *, CASE WHEN sw * sxx - sx * sx > 1e-9 THEN (sw * sxy - sx * sy) / (sw * sxx - sx * sx) END AS tau FROM sums),
lines AS (SELECT *, (sy - tau * sx) / sw AS icpt FROM slopes),
curves_ AS (SELECT feature_id, tau, -icpt / CASE WHEN abs(tau) > 1e-12 THEN tau END AS alpha,
    sqrt(greatest((n0 * (-{LOGIT} - icpt) * (-{LOGIT} - icpt) - 2 * tau * (-{LOGIT} - icpt) * s0 + tau * tau * q0 + n1 * ({LOGIT} - icpt) * ({LOGIT} - icpt) - 2 * tau * ({LOGIT} - icpt) * s1 + tau * tau * q1) / CASE WHEN nobs > 2 THEN nobs - 2 END, 0.0)) AS sigma,
    (s0 + s1) / nobs AS xbar, (q0 + q1) - nobs * ((s0 + s1) / nobs) * ((s0 + s1) / nobs) AS dev, nobs, s0 / nullif(CAST(n0 AS DOUBLE), 0) AS lo, s1 / nullif(CAST(n1 AS DOUBLE), 0) AS hi FROM lines),
curves AS MATERIALIZED (SELECT *, coalesce(lo < hi AND tau > 0 AND nobs > 2 AND dev > 1e-9, false) AS active FROM curves_)"""


def _area(b: str) -> str:
    return f"list_sum(list_transform(range(0, 65), lambda i: CASE WHEN i IN (0, 64) THEN 1.0 WHEN i % 2 = 1 THEN 4.0 ELSE 2.0 END * pow(greatest(cos(({b}) / 64 * i), 0.0), nobs - 3))) * ({b}) / 64 / 3"


ENTRIES = f"""
whole AS MATERIALIZED (SELECT feature_id, least(pi() / 2, 9.0 / sqrt(nobs - 2)) AS upto, {_area('least(pi() / 2, 9.0 / sqrt(nobs - 2))')} AS area FROM curves WHERE active),
open_ AS (SELECT pair_id, feature_id, x, tau, alpha, nobs, area, upto, 1.0 / (greatest(sigma, 1e-9) * sqrt(1 + 1 / nobs + (x - xbar) * (x - xbar) / dev)) AS q FROM incidence ANTI JOIN easy USING (pair_id) JOIN curves USING (feature_id) JOIN whole USING (feature_id) WHERE active),
ends AS (SELECT *, least(atan(q / sqrt(nobs - 2)), upto) AS b FROM open_),
entries AS MATERIALIZED (SELECT pair_id, feature_id, x, tau, alpha, least(1.0, {_area('b')} / area) AS raw, (1 + least(1.0, {_area('b')} / area)) / 2 AS theta FROM ends)"""

ROUND = f"{PAIRS}, {EASY}, {INCIDENCE}, {STATS}, {CURVES}, {ENTRIES}"
SUPPORT = "sup AS MATERIALIZED (SELECT pair_id, sum(ln(least(theta, 1 - 1e-12) / (1 - least(theta, 1 - 1e-12)))) AS log_odds, count(*) AS features FROM entries GROUP BY pair_id)"
APPROX = "approx AS MATERIALIZED (SELECT pair_id, sum(theta * tau * (x - alpha)) AS z FROM entries GROUP BY pair_id)"
LOGISTIC = "1 / (1 + exp(-least(greatest({0}, -700.0), 700.0)))"


def entropy_sql(p: str) -> str:
    part = "CASE WHEN {0} <= 0 OR {0} >= 1 THEN 0.0 ELSE -({0}) * log2({0}) END"
    return f"({part.format(p)} + {part.format(f'(1 - {p})')})"


def kmeans_sql(rounds: int = 10, cols: tuple[str, ...] = W.PARTS) -> str:
    """CTEs c0 .. c<rounds>: the centres (one row), and clustered (pair_id, label)."""
    parts = ["c0 AS MATERIALIZED (SELECT " + ", ".join([f"min({c}) AS a_{c}" for c in cols] + [f"max({c}) AS b_{c}" for c in cols]) + " FROM pairs)"]
    dist = lambda s: " + ".join(f"({c} - {s}_{c}) * ({c} - {s}_{c})" for c in cols)
    for k in range(rounds):
        own = ", ".join([f"coalesce(avg({c}) FILTER (WHERE NOT m), any_value(a_{c})) AS a_{c}" for c in cols] + [f"coalesce(avg({c}) FILTER (WHERE m), any_value(b_{c})) AS b_{c}" for c in cols])
        parts.append(f"c{k + 1} AS MATERIALIZED (SELECT {own} FROM (SELECT *, ({dist('b')}) < ({dist('a')}) AS m FROM pairs, c{k}))")
    parts.append(f"clustered AS MATERIALIZED (SELECT pair_id, CAST(({dist('b')}) < ({dist('a')}) AS INT) AS label FROM pairs, c{rounds})")
    return ", ".join(parts)
