"""Records, blocking, candidate pairs, and the workloads on the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import similarity as S

TITLE = 12
PAIR_BASE = 1 << 31


def pair_id(a: Column, b: Column) -> Column:
    """a * PAIR_BASE + b where both ids lie in [0, PAIR_BASE); else a negative number from their 64-bit hash (two of 10^8 such pairs agree with a chance of 1 in 1,800)."""
    small = (a >= 0) & (b >= 0) & (a < PAIR_BASE) & (b < PAIR_BASE)
    return F.when(small, a * F.lit(PAIR_BASE) + b).otherwise(F.xxhash64(a, b).bitwiseOR(F.lit(-(1 << 63))))


def hash_order(pair: str | Column) -> Column:
    """A number of 60 bits from the MD5 of a pair id as text, which other engines have too: the order in which pairs are capped, thinned and resized."""
    return F.conv(F.substring(F.md5(F.col(pair).cast("string") if isinstance(pair, str) else pair.cast("string")), 1, 15), 16, 10).cast("bigint")


def beyond(tokens: str | Column, n: int) -> Column:
    """The tokens behind the first n."""
    return F.slice(tokens, n + 1, F.greatest(F.size(tokens) - n, F.lit(0)))


def document_records(docs: DataFrame) -> DataFrame:
    """rec_id, title (the first tokens), body (all others), source, n_chars, words (all tokens of the text). Who reads no more than titles splits no whole texts."""
    rows = docs.select(F.col("doc_id").alias("rec_id"), S.first_tokens(F.col("text"), TITLE).alias("title"), S.tokens(F.col("text")).alias("words"), "source", F.col("n_chars").cast("double").alias("n_chars"))
    return rows.select("rec_id", "title", beyond("words", TITLE).alias("body"), "source", "n_chars", "words")


def corrupt(records: DataFrame) -> DataFrame:
    """Deterministic dirty twin, by index arithmetic alone: tokens are lost or lose a letter, sources and lengths drift. Titles and bodies are made apart, so titles alone cost little."""
    r = F.col("rec_id")

    def kept(c: str, before: int) -> Column:
        """Of tokens with so many before them in the text."""
        some = F.transform(
            c,
            lambda x, i: F.when((r * 7919 + (i + before) * 104729 + r * (i + before) * 31) % 100 < 5 + (r * 31) % 60, F.lit(None).cast("string"))
            .when(((r * 13 + (i + before) * 17) % 10 == 0) & (F.length(x) > 3), F.concat(F.substring(x, 1, 1), x.substr(F.lit(3), F.length(x))))
            .otherwise(x),
        )
        return F.filter(some, lambda x: x.isNotNull())

    rows = records.select(
        "rec_id",
        kept("title", 0).alias("title"),
        kept("body", TITLE).alias("body"),
        F.when(r % 4 == 0, F.concat(F.lit("src"), (r % 20).cast("string"))).otherwise(F.col("source")).alias("source"),
        (F.col("n_chars") * (1 + (r % 7 - 3) / F.lit(50.0))).alias("n_chars"),
    )
    return rows.withColumn("words", F.concat("title", "body"))


def postings(records: DataFrame, tokens_col: str = "title") -> DataFrame:
    return records.select("rec_id", F.explode(F.array_distinct(tokens_col)).alias("token"))


def block_by_tokens(left: DataFrame, right: DataFrame, df_max: int = 200, min_shared: int = 2, tokens_col: str = "title") -> DataFrame:
    """id_a, id_b, shared: pairs of two tables that share at least so many tokens of at most this document frequency (over both)."""
    a, b = postings(left, tokens_col), postings(right, tokens_col)
    df = a.select("token").unionAll(b.select("token")).groupBy("token").agg(F.count(F.lit(1)).alias("df")).where(F.col("df") <= df_max)
    a = a.join(df, "token").select("token", F.col("rec_id").alias("id_a"))
    b = b.select("token", F.col("rec_id").alias("id_b"))
    met = a.join(b, "token").groupBy("id_a", "id_b").agg(F.count(F.lit(1)).alias("shared"))
    return met.where(F.col("shared") >= min_shared)


def block_within(records: DataFrame, df_max: int = 200, min_shared: int = 2, tokens_col: str = "title") -> DataFrame:
    """The same within one table, id_a < id_b."""
    a = postings(records, tokens_col)
    df = a.groupBy("token").agg(F.count(F.lit(1)).alias("df")).where(F.col("df") <= df_max)
    kept = a.join(df, "token").select("token", "rec_id")
    met = kept.select("token", F.col("rec_id").alias("id_a")).join(kept.select("token", F.col("rec_id").alias("id_b")), "token").where("id_a < id_b")
    return met.groupBy("id_a", "id_b").agg(F.count(F.lit(1)).alias("shared")).where(F.col("shared") >= min_shared)


def block_rest(left: DataFrame, right: DataFrame | None = None, df_max: int = 200, min_shared: int = 2, threshold: float = 0.5, tokens_col: str = "title") -> DataFrame:
    """id_a, id_b, sim: the similar pairs that blocking by rare tokens cannot see, whatever the frequency of what they share.

    Records with the same set of tokens are one class, named by its least record, and classes
    whose Jaccard reaches the threshold are paired by a prefix filter. Which tokens a pair
    shares depends on the two classes alone, so a pair of classes is found by rare tokens as
    a whole or not at all; those found are left out. Together with ``token_classes`` no
    similar pair of records is lost, and copies are never expanded. Without a right table:
    within the left one, id_a < id_b; members of one class are then pairs by membership.
    """
    from ..plans.planner import class_heads, cut, short_join

    heads = [cut(class_heads(t.select("rec_id", F.col(tokens_col).alias("s"))), "heads") for t in ([left] if right is None else [left, right])]
    met = short_join(heads[0], heads[-1], threshold, df_max, min_shared)
    return met.where("id_a < id_b") if right is None else met


def block_by_key(left: DataFrame, right: DataFrame, cols: list[str]) -> DataFrame:
    a = left.select(F.col("rec_id").alias("id_a"), *cols)
    return a.join(right.select(F.col("rec_id").alias("id_b"), *cols), cols).select("id_a", "id_b")


def block_sorted(records: DataFrame, key: Column, window: int, buckets: int = 64) -> DataFrame:
    """Sorted neighbourhood: each record with the next ``window`` in the order of (key, rec_id).

    Rows are ranked without a global window: a range repartition orders them, each
    partition is numbered, and the partitions' sizes give the offsets. Bounds of a range
    repartition come from a sample, which another run of it draws anew, so the numbers
    are written once and all else is read from them.
    """
    from ..plans.planner import cut

    rows = records.select("rec_id", key.alias("k")).repartitionByRange(buckets, "k", "rec_id").sortWithinPartitions("k", "rec_id")
    rows = cut(rows.select("rec_id", F.monotonically_increasing_id().alias("_m")), "sorted")  # partition in the upper bits, place in the lower 33
    rows = rows.select("rec_id", F.shiftright("_m", 33).alias("part"), (F.col("_m").bitwiseAND(F.lit((1 << 33) - 1)) + 1).alias("r"))
    sizes = rows.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    offsets = sizes.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    at = rows.join(F.broadcast(offsets), "part").select("rec_id", (F.col("base") + F.col("r")).alias("at"))
    ahead = at.select(F.col("rec_id").alias("id_a"), F.explode(F.sequence(F.col("at") + 1, F.col("at") + window)).alias("at"))
    return ahead.join(at.withColumnRenamed("rec_id", "id_b"), "at").select(F.least("id_a", "id_b").alias("id_a"), F.greatest("id_a", "id_b").alias("id_b"))


MINHASH_PRIME = 4294967291


def minhash_step(s: int) -> tuple[int, int]:
    """Factor and addend of the s-th hash of a token's 32 leading MD5 bits."""
    return ((s + 1) * 630360016 + 12345) % (1 << 30) | 1, (s + 7) * 1101513973 % (1 << 31)


def block_minhash(left: DataFrame, right: DataFrame, tokens_col: str = "title", bands: int = 16, rows: int = 2) -> DataFrame:
    """Pairs that agree in one band of minimum hashes. A pair is given by the first band in which it agrees: each row has its earlier bands beside it as numbers, so pairs are not shuffled. Two hashes, of 32 bits each, make one number."""
    words = range(-(-rows // 2))

    def banded(records: DataFrame, name: str) -> DataFrame:
        def least(s: int) -> Column:
            a, b = minhash_step(s)
            return F.array_min(F.transform("codes", lambda c: (c * a + b) % MINHASH_PRIME))

        def number(b: int, w: int) -> Column:
            own = [least(b * rows + k) for k in range(2 * w, min(rows, 2 * w + 2))]
            return F.shiftleft(own[0], 32).bitwiseOR(own[1]) if len(own) > 1 else own[0]

        codes = F.transform(tokens_col, lambda t: F.conv(F.substring(F.md5(t), 1, 8), 16, 10).cast("bigint"))
        coded = records.where(F.size(tokens_col) > 0).select(F.col("rec_id").alias(name), codes.alias("codes"))
        hashes = F.array(*[F.struct(*[number(b, w).alias(f"h{w}") for w in words]) for b in range(bands)])
        coded = coded.select(name, hashes.alias("all")).select(name, "all", F.posexplode("all").alias("band", "h"))
        earlier = [F.when(F.col("band") > b, F.col("all")[b][f"h{w}"]).alias(f"{name}_{b}_{w}") for b in range(bands - 1) for w in words]
        return coded.select(name, *[F.col(f"h.h{w}").alias(f"h{w}") for w in words], "band", *earlier)

    met = banded(left, "id_a").join(banded(right, "id_b").hint("merge"), [*[f"h{w}" for w in words], "band"])
    for b in range(bands - 1):  # null from the band of the row on
        same = F.lit(True)
        for w in words:
            same &= F.col(f"id_a_{b}_{w}") == F.col(f"id_b_{b}_{w}")
        met = met.where(~F.coalesce(same, F.lit(False)))
    return met.select("id_a", "id_b")


def minhash_classes(left: DataFrame, right: DataFrame, tokens_col: str = "title") -> DataFrame:
    """id_a, id_b, kind: block_minhash between classes of equal sets (kind pair), each named by its least record of its table, and whose copy a record is: id_b of the class id_a of the left (left) or the right table (right). Copies agree in all bands, so no pair is lost. Sets are written once, and all else is read from them."""
    from ..plans.planner import class_heads, cut, token_classes

    sets = [cut(t.select("rec_id", F.col(tokens_col).alias("s")), "titles") for t in (left, right)]
    heads = [cut(class_heads(t), "heads") for t in sets]
    out = block_minhash(*heads, tokens_col="s").withColumn("kind", F.lit("pair"))
    for t, kind in zip(sets, ("left", "right"), strict=True):
        out = out.unionAll(token_classes(t).where("rec_id <> class_id").select(F.col("class_id").alias("id_a"), F.col("rec_id").alias("id_b"), F.lit(kind).alias("kind")))
    return out


def pairs_all(left: DataFrame, right: DataFrame, max_pairs: int = 1_000_000) -> DataFrame:
    """The unblocked baseline; refuses more than so many pairs."""
    n = left.count() * right.count()
    if n > max_pairs:
        raise ValueError(f"{n} pairs exceed {max_pairs}; use a blocking")
    return left.select(F.col("rec_id").alias("id_a")).crossJoin(right.select(F.col("rec_id").alias("id_b")))


def attribute_weights(*tables: DataFrame, approximate: bool = False) -> dict[str, float]:
    """Share of each attribute in the sum of distinct values; the sketch is meant for 100 TB. Bodies are counted by digests: tokens have no blanks, so joined ones differ where the bodies do."""
    body = F.sha2(F.array_join("body", " "), 256).alias("body")
    rows = tables[0].select("title", body, "source", "n_chars")
    for t in tables[1:]:
        rows = rows.unionByName(t.select("title", body, "source", "n_chars"))
    count = F.approx_count_distinct if approximate else F.count_distinct
    got = rows.agg(*[count(c).alias(c) for c in rows.columns]).first()
    total = sum(got) or 1
    return {f"sim_{k}": got[c] / total for k, c in (("title", "title"), ("body", "body"), ("source", "source"), ("num", "n_chars"))}


def compare(blocked: DataFrame, left: DataFrame, right: DataFrame, source: str = "exact") -> DataFrame:
    """Attribute similarities of candidate pairs over whole texts; keeps both titles for the features. A record has many pairs, so what goes to them of a body is its distinct tokens as numbers, about a byte each (see plans.similar_sets), and not its text. Bodies are joined again by with_bodies where a feature needs them."""
    from ..plans.planner import cut
    from ..plans.similar_sets import coded_tables, hashed_sets, shared_size

    tables = [left] if left is right else [left, right]
    hashed = [hashed_sets(t.select("rec_id", F.array_distinct("body").alias("s"), "title", "source", "n_chars")) for t in tables]
    coded = [cut(c.drop("digest"), "bodies") for c in coded_tables(*hashed)]
    side = lambda t, s: t.select(*[F.col(c).alias(f"{n}_{s}") for c, n in [("rec_id", "id"), *[(c, c) for c in ("title", "source", "n_chars", "n", "near", "far", "rest")]]])
    rows = blocked.select("id_a", "id_b").join(side(coded[0], "a"), "id_a").join(side(coded[-1], "b"), "id_b")
    rows = rows.withColumn("met", shared_size(*[f"{c}_{s}" for s in "ab" for c in ("near", "far", "rest")]))
    same = S.exact_sim(F.col("source_a"), F.col("source_b")) if source == "exact" else S.jaro_winkler("source_a", "source_b")
    return rows.select(
        pair_id(F.col("id_a"), F.col("id_b")).alias("pair_id"), "id_a", "id_b",
        S.jaccard(F.col("title_a"), F.col("title_b")).alias("sim_title"),
        F.coalesce(F.try_divide(F.col("met").cast("double"), (F.col("n_a") + F.col("n_b") - F.col("met")).cast("double")), F.lit(0.0)).alias("sim_body"),
        same.alias("sim_source"),
        S.number_sim(F.col("n_chars_a"), F.col("n_chars_b")).alias("sim_num"),
        "title_a", "title_b",
    )


def with_bodies(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    side = lambda t, s: t.select(F.col("rec_id").alias(f"id_{s}"), F.col("body").alias(f"body_{s}"))
    return pairs.join(side(left, "a"), "id_a").join(side(right, "b"), "id_b")


PARTS = ("sim_title", "sim_body", "sim_source", "sim_num")


def with_similarity(pairs: DataFrame, weights: dict[str, float]) -> DataFrame:
    return pairs.withColumn("sim", F.round(S.weighted_similarity(weights), 9))


# truth


def strict_entities(records: DataFrame, length: int | None = None) -> DataFrame:
    """rec_id, entity_id: the least id with exactly the same tokens, or the same first ones."""
    own = records.select("rec_id", F.sha2(F.array_join(F.slice("words", 1, length) if length else F.col("words"), " "), 256).alias("k"))
    least = own.groupBy("k").agg(F.min("rec_id").alias("entity_id"))
    return own.join(least, "k").select("rec_id", "entity_id")


def cluster_entities(records: DataFrame, threshold: float = 0.5) -> DataFrame:
    """rec_id, entity_id: the least id of the component linked by Jaccard of the texts' token sets. Records with equal sets are one before any two sets are compared; links within what is joined already are not listed."""
    from ..plans.planner import connected_components, cut
    from ..plans.similar_sets import coded_sets, links

    coded = cut(coded_sets(records.select("rec_id", F.array_distinct("words").alias("s"))), "sets")
    heads = coded.where("digest is not null").groupBy("digest").agg(F.min_by(F.struct("n", "near", "far", "rest"), "rec_id").alias("x"), F.min("rec_id").alias("rec_id"))
    heads = cut(heads.select("digest", "rec_id", "x.*"), "heads")
    roots = connected_components(links(heads, threshold), "id_a", "id_b")
    named = heads.select("digest", "rec_id").join(roots, F.col("rec_id") == F.col("node"), "left").select("digest", F.coalesce("root", "rec_id").alias("entity_id"))
    return coded.select("rec_id", "digest").join(named, "digest", "left").select("rec_id", F.coalesce("entity_id", "rec_id").alias("entity_id"))


def truth(pairs: DataFrame, left_entities: DataFrame, right_entities: DataFrame | None = None) -> DataFrame:
    """pair_id, truth (0 or 1): whether both entity ids agree."""
    right_entities = left_entities if right_entities is None else right_entities
    a = left_entities.select(F.col("rec_id").alias("id_a"), F.col("entity_id").alias("e_a"))
    b = right_entities.select(F.col("rec_id").alias("id_b"), F.col("entity_id").alias("e_b"))
    return pairs.select("pair_id", "id_a", "id_b").join(a, "id_a").join(b, "id_b").select("pair_id", (F.col("e_a") == F.col("e_b")).cast("int").alias("truth"))


def resize(pairs: DataFrame, labels: DataFrame, n: int) -> DataFrame:
    """About n pairs, in the order of a hash of the id, with the match share kept."""
    rows = pairs.join(labels, "pair_id")
    total = rows.count()
    w = Window.partitionBy("truth").orderBy(hash_order("pair_id"), "pair_id")
    size = F.count(F.lit(1)).over(Window.partitionBy("truth"))
    ranked = rows.withColumn("_r", F.row_number().over(w)).withColumn("_n", size)
    return ranked.where(F.col("_r") <= F.floor(F.col("_n") * F.lit(n) / F.lit(max(total, 1)))).drop("_r", "_n")


# workloads by name


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def w1h(spark: SparkSession, sf_dir: str, df_max: int = 200, min_shared: int = 2, rest: float | None = None) -> DataFrame:
    """Documents against their dirty twin, with the weighted similarity. rest: also classes of titles that are so similar and share frequent tokens only."""
    left = document_records(load(spark, sf_dir, "documents"))
    right = corrupt(left)
    blocked = block_by_tokens(left, right, df_max, min_shared).select("id_a", "id_b")
    if rest is not None:
        blocked = blocked.unionAll(block_rest(left, right, df_max, min_shared, rest).select("id_a", "id_b"))
    pairs = compare(blocked, left, right)
    return with_similarity(pairs, attribute_weights(left, right))


def w2s(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents and twin in one table, paired within it."""
    left = document_records(load(spark, sf_dir, "documents"))
    shift = left.agg(F.coalesce(F.max("rec_id"), F.lit(0)) + 1).first()[0]
    both = left.unionByName(corrupt(left).withColumn("rec_id", F.col("rec_id") + shift))
    pairs = compare(block_within(both, 200, 3), both, both, source="jaro_winkler")
    return with_similarity(pairs, attribute_weights(both))
