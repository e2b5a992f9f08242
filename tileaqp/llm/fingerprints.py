"""Document fingerprints: SimHash over weighted terms, and search by permuted block tables.

Terms are pairs of following words (a single word with nothing); each votes with its
length in characters, plus or minus, on the 64 bits of its hash. Two bits are summed
in one 64-bit number, so 32 sums give all votes. A bit is set if the votes for it have
more than half of the weight; no vote at all gives zero.

Search cuts fingerprints into ``radius + AGREE`` blocks: two that differ in at most
``radius`` bits agree in at least ``AGREE`` of them. There is a table for every choice of so many
blocks, filing each distinct fingerprint under these blocks' bits (about 32 for a radius of
3), so that unequal fingerprints seldom meet by chance.

Null texts are empty. Texts count whole. Equal texts have equal fingerprints, repeated
rows each their own row. Keys are whole numbers, or strings that hold them (others
count as null); the result has them as given. Rows with a null key come last in descending order; rows with
the same key are ordered by a hash of the text. Other columns don't matter. A single
row is its own next document; an empty table gives an empty result. Only DataFrame
expressions are used.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..runtime import durable

PAIR_MASK = (1 << 32) | 1
#: Blocks that two fingerprints must agree in to meet.
AGREE = 3


def _terms(body: Column) -> Column:
    words = F.filter(F.split(F.translate(body, "\n\t\r\x0b\x0c", "     "), " "), lambda w: w != "")
    return F.arrays_zip(words.alias("a"), F.slice(words, 2, F.greatest(F.size(words) - 1, F.lit(0))).alias("b"))


def fingerprints(rows: DataFrame, by: list[str], body: str) -> DataFrame:
    """(by..., fp) for rows whose ``by`` is unique; rows without terms are not returned (their fingerprint is zero)."""
    terms = rows.select(*by, F.inline(_terms(F.col(body))).alias("_a", "_b"))
    hashed = terms.select(*by, F.xxhash64("_a", "_b").alias("_h"), (F.length("_a") + F.coalesce(F.length("_b"), F.lit(0))).cast("long").alias("_w"))
    sums = [F.sum(F.shiftrightunsigned("_h", i).bitwiseAND(F.lit(PAIR_MASK)) * F.col("_w")).alias(f"_s{i}") for i in range(32)]
    votes = hashed.groupBy(*by).agg(F.sum("_w").alias("_all"), *sums)
    fp = F.lit(0).cast("long")
    for i in range(32):
        low, high = F.col(f"_s{i}").bitwiseAND(F.lit(0xFFFFFFFF)), F.shiftrightunsigned(f"_s{i}", 32)
        for votes_for, bit in ((low, i), (high, i + 32)):
            fp = fp.bitwiseOR(F.when(votes_for * 2 > F.col("_all"), F.shiftleft(F.lit(1).cast("long"), bit)).otherwise(F.lit(0).cast("long")))
    return votes.select(*by, fp.alias("fp"))


def likeness(a: str, b: str) -> Column:
    return 1 - F.bit_count(F.col(a).bitwiseXOR(F.col(b))) / F.lit(64.0)


def _bucket(key: Column, bounds: list[int]) -> Column:
    """How many of the sorted bounds are not above the key, by halving; -1 for null."""
    table = F.lit(bounds) if bounds else F.array().cast("array<long>")
    steps = [1 << i for i in reversed(range(max(1, len(bounds).bit_length())))]

    def halve(at: Column, step: Column) -> Column:
        to = at + step
        return F.when((to <= len(bounds)) & (F.get(table, to - 1) <= key), to).otherwise(at)

    return F.when(key.isNull(), F.lit(-1)).otherwise(F.aggregate(F.array(*map(F.lit, steps)), F.lit(0), halve))


def with_next(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(bucket, place, key, named, body, next_body, next_bucket, next_place): every row and the one after it by descending key."""
    spark = docs.sparkSession
    rows = docs.select(F.expr(f"try_cast(`{key}` AS long)").alias("key"), F.col(f"`{key}`").alias("named"), F.coalesce(F.col(f"`{text}`").cast("string"), F.lit("")).alias("body"))
    n = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    got = rows.agg(F.percentile_approx("key", [i / n for i in range(1, n)], 20 * n)).first()[0]  # as many numbers as buckets
    rows = rows.withColumn("bucket", _bucket(F.col("key"), sorted(set(got or []))))
    order = [F.col("key").desc_nulls_last(), F.xxhash64("body"), F.col("body")]
    # the first row of each bucket follows the last one of the bucket above; there are as many as buckets
    tops = [(r.bucket, r.top) for r in rows.groupBy("bucket").agg(F.max("key").alias("top")).collect()]
    tops.sort(reverse=True)
    after = spark.createDataFrame([(b, *tops[(i + 1) % len(tops)]) for i, (b, _) in enumerate(tops)], "bucket int, next_bucket int, top long")
    firsts = rows.select("key", "body").join(F.broadcast(after), F.col("key").eqNullSafe(F.col("top")))
    firsts = firsts.groupBy(F.col("bucket").alias("b"), "next_bucket").agg(F.min_by("body", F.struct(F.xxhash64("body"), "body")).alias("first_body"))
    w = Window.partitionBy("bucket").orderBy(*order)
    placed = rows.select("bucket", "key", "named", "body", F.row_number().over(w).alias("place"), F.lead("body").over(w).alias("lead"))
    joined = placed.join(durable(firsts, "firsts").hint("merge"), F.col("bucket") == F.col("b"))
    last = F.col("lead").isNull()
    return joined.select(
        "bucket", "place", "key", "named", "body", F.coalesce("lead", "first_body").alias("next_body"),
        F.when(last, F.col("next_bucket")).otherwise(F.col("bucket")).alias("next_bucket"), F.when(last, 1).otherwise(F.col("place") + 1).alias("next_place"),
    )


def fingerprints_and_edits(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Each row's fingerprint, that of its text with the last third taken from the next row's start, and the next row's."""
    rows = with_next(docs, key, text)
    n = F.length("body")
    third = F.floor(n / 3).cast("int")
    rows = rows.withColumn("edited", F.concat(F.col("body").substr(F.lit(1), n - third), F.col("next_body").substr(F.lit(1), third)))
    facts = rows.select("bucket", "place", "named", n.cast("long").alias("n_chars"), F.sha2("edited", 256).alias("edited_sha256"), "next_bucket", "next_place")
    both = rows.select("bucket", "place", F.posexplode(F.array("body", "edited")).alias("kind", "words"))
    prints = fingerprints(both, ["bucket", "place", "kind"], "words")
    prints = durable(prints.groupBy("bucket", "place").agg(F.max(F.when(F.col("kind") == 0, F.col("fp"))).alias("fp"), F.max(F.when(F.col("kind") == 1, F.col("fp"))).alias("edited_fp")), "prints")
    facts = durable(facts, "facts")
    zero = lambda c: F.coalesce(c, F.lit(0).cast("long"))
    out = facts.join(prints, ["bucket", "place"], "left")
    following = prints.select(F.col("bucket").alias("next_bucket"), F.col("place").alias("next_place"), F.col("fp").alias("next_fp"))
    out = out.join(following, ["next_bucket", "next_place"], "left").withColumns({c: zero(F.col(c)) for c in ("fp", "edited_fp", "next_fp")})
    return out.select(F.col("named").alias(key), "n_chars", "edited_sha256", "fp", "edited_fp", likeness("fp", "edited_fp").alias("near_edited"), likeness("fp", "next_fp").alias("near_next"))


def within(queries: DataFrame, table: DataFrame, radius: int = 3) -> DataFrame:
    """(fp, other, distance): all distinct fingerprints of ``table`` at most ``radius`` bits from those of ``queries``."""
    if not 0 <= radius <= 6:
        raise ValueError("a radius from 0 to 6")
    n = radius + AGREE
    cuts = [64 * i // n for i in range(n + 1)]
    masks = [((1 << b) - 1) ^ ((1 << a) - 1) for a, b in zip(cuts, cuts[1:], strict=False)]
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    chosen = list(combinations(range(n), AGREE))
    permuted = [signed(sum(masks[i] for i in c)) for c in chosen]

    def filed(df: DataFrame, name: str) -> DataFrame:
        fp = F.col("fp")
        entries = [F.struct(F.lit(t).alias("t"), fp.bitwiseAND(F.lit(m)).alias("v")) for t, m in enumerate(permuted)]
        return df.select("fp").distinct().select(fp.alias(name), F.inline(F.array(*entries)))

    pairs = filed(queries, "fp").join(filed(table, "other"), ["t", "v"])
    x = F.col("fp").bitwiseXOR(F.col("other"))
    # a pair that meets in several tables is kept by the first of them: that of the first blocks that agree
    agrees = F.array(*(F.when(x.bitwiseAND(F.lit(signed(m))) == 0, i) for i, m in enumerate(masks)))
    first = F.slice(F.array_compact(agrees), 1, AGREE)
    own = F.array(*(F.array(*map(F.lit, c)) for c in chosen))[F.col("t")]
    return pairs.filter((F.bit_count(x) <= radius) & (first == own)).select("fp", "other", F.bit_count(x).alias("distance"))
