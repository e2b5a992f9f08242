"""Extendible hashing: rows go to shards named by a prefix of their hash, as long as it takes to fit a byte limit.

The hash is 62 bits of a digest of the key; the last half of a second digest, over
key and row, follows it, so that a key with more rows than a shard may hold is split
as well. The directory starts with all rows in one bucket; a bucket over the limit is
split on the next bit, and only that one. Sizes for ``STEP`` bits at a time come from
one pre-aggregated count of prefixes, of which only those in buckets still too large
are counted again with longer prefixes.

A null text has no bytes; a null key hashes like any value. Repeated rows that are
alike in all columns can't be told apart: they share a shard even over the limit, as
does a single row that is larger; such a shard is marked oversized. Other columns
don't matter for keys, but are part of the second digest; columns that have the name
of one of the result (``FRESH``) are left out of it. An empty table gives an
empty result. Only DataFrame expressions are used.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..runtime import durable

#: Bytes of text that a shard may hold.
LIMIT = 64 << 20
#: Bits of the prefix that one pass of counting resolves.
STEP = 8
#: Bits of the key's digest, and of the row's digest after it.
KEY_BITS, ROW_BITS = 62, 60

#: The columns that the result adds.
FRESH = ("shard", "n_bytes", "shard_rows", "shard_bytes", "oversized", "shard_depth")


def _digest_bits(value: Column, bits: int) -> Column:
    """The first bits of an MD5 digest, as '0' and '1'."""
    digest = F.md5(value)
    half = lambda at: F.lpad(F.conv(F.substring(digest, at, 8), 16, 2), 32, "0")
    return F.concat(half(1), half(9)).substr(F.lit(1), F.lit(bits))


def with_hash(docs: DataFrame, key: str = "doc_id", text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """(_row, _bits, _bytes): a row's columns in one struct, where no name can clash, its hash as a string of bits, and its size."""
    name = F.coalesce(F.col(f"`{key}`").cast("string"), F.lit("null"))
    row = F.to_json(F.struct(*(F.col(f"`{c}`") for c in docs.columns)))
    bits = F.concat(_digest_bits(name.cast("binary"), KEY_BITS), _digest_bits(row.cast("binary"), ROW_BITS))
    size = F.coalesce(F.octet_length(F.col(f"`{text}`").cast("string")), F.lit(0)).cast("long")
    own = F.struct(*(F.col(f"`{c}`") for c in (docs.columns if keep is None else keep)))
    return docs.select(own.alias("_row"), bits.alias("_bits"), size.alias("_bytes"))


def directory(rows: DataFrame, limit: int = LIMIT, step: int = STEP) -> DataFrame:
    """(prefix, n_rows, n_bytes, oversized): the leaves of the directory over rows (_bits, _bytes)."""
    whole = KEY_BITS + ROW_BITS
    leaves, open_rows, depth = [], rows.select("_bits", "_bytes"), 0
    while True:
        to = min(depth + step, whole)
        counted = open_rows.groupBy(F.substring("_bits", 1, to).alias("long")).agg(F.count("*").alias("n_rows"), F.sum("_bytes").alias("n_bytes"))
        # every bucket on the way from the open ones down to the longest prefixes
        levels = counted.select(F.explode(F.sequence(F.lit(depth), F.lit(to))).alias("d"), "long", "n_rows", "n_bytes")
        buckets = levels.groupBy("d", F.expr("substring(long, 1, d)").alias("prefix")).agg(F.sum("n_rows").alias("n_rows"), F.sum("n_bytes").alias("n_bytes"))
        buckets = durable(buckets, "buckets")
        large = buckets.filter(F.col("n_bytes") > limit)
        above = large.select((F.col("d") + 1).alias("d"), F.col("prefix").alias("parent"))
        reached = buckets.withColumn("parent", F.expr("substring(prefix, 1, d - 1)")).join(above, ["d", "parent"], "left_semi").select("d", "prefix", "n_rows", "n_bytes")
        if depth == 0:
            reached = reached.unionByName(buckets.filter("d = 0"))
        last = (F.col("d") == whole) & (F.col("n_bytes") > limit)
        leaves.append(reached.filter((F.col("n_bytes") <= limit) | last).select("prefix", "n_rows", "n_bytes", (F.col("n_bytes") > limit).alias("oversized")))
        still = large.filter(F.col("d") == to).select("prefix")
        if to == whole or still.isEmpty():
            break
        depth = to
        open_rows = rows.select("_bits", "_bytes", F.substring("_bits", 1, to).alias("prefix")).join(still, "prefix", "left_semi").select("_bits", "_bytes")
    out = leaves[0]
    for more in leaves[1:]:
        out = out.unionByName(more)
    return durable(out, "directory")


def assign(docs: DataFrame, key: str = "doc_id", text: str = "text", limit: int = LIMIT, step: int = STEP, keep: list[str] | None = None) -> DataFrame:
    """The rows (or their columns in ``keep``) with shard (the prefix), shard_depth, and what the shard holds."""
    keep = [c for c in (docs.columns if keep is None else keep) if c not in FRESH]
    hashed = with_hash(docs, key, text, keep)
    rows = durable(hashed.select("_bits", "_bytes"), "hashes") if set(keep) != {key} else (hashed := durable(hashed, "hashes"))
    leaves = directory(rows, limit, step)
    depths = [r.d for r in leaves.select(F.length("prefix").alias("d")).distinct().collect()]  # at most one number per bit
    prefixes = F.array(*(F.substring("_bits", 1, d) if d else F.lit("") for d in sorted(depths)))
    # leaves exclude one another, so exactly one of a row's prefixes is there
    tried = hashed.select("_row", F.col("_bytes").alias("n_bytes"), F.explode(prefixes).alias("prefix"))
    named = leaves.select("prefix", F.col("n_rows").alias("shard_rows"), F.col("n_bytes").alias("shard_bytes"), "oversized")
    return tried.join(named, "prefix").select(*(F.col("_row")[c].alias(c) for c in keep), "n_bytes", F.col("prefix").alias("shard"), "shard_rows", "shard_bytes", "oversized", F.length("prefix").alias("shard_depth"))


def write(docs: DataFrame, path: str, key: str = "doc_id", text: str = "text", limit: int = LIMIT) -> None:
    """Write each shard as a file under ``path``/shard=<prefix>; a row's shard doesn't depend on the others' order."""
    laid = assign(docs, key, text, limit).drop("n_bytes", "shard_rows", "shard_bytes", "oversized", "shard_depth")
    laid.repartition("shard").write.partitionBy("shard").parquet(path)
