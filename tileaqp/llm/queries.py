"""The registered queries of this subpackage: each applies its operator to whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..runtime import durable
from . import chat, decontaminate, fingerprints, packing, pii, quality, sharding, simhash_dedup, suffix_dedup, toxicity

#: Key of the surrogates here; a deployment passes its own secret.
PII_KEY = "documents-surrogates-1"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign(table(spark, sf_dir, "documents"), keep=["doc_id"])


def sharding_small_limit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same with shards of 128 KiB, so that small tables split too."""
    return sharding.assign(table(spark, sf_dir, "documents"), limit=128 << 10, keep=["doc_id"])


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(table(spark, sf_dir, "documents"))


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.find(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), keep=["doc_id"])
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"), "spans")


def _classified(spark: SparkSession, sf_dir: str, method, label: str, threshold: float) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = method.fit(docs, table(spark, sf_dir, "labels"), label)
    scored = method.score(docs, model, keep=["doc_id"])
    return scored.select("doc_id", quality.held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _classified(spark, sf_dir, toxicity, "toxic", 0.5)


def op5_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash_dedup.components_of(table(spark, sf_dir, "documents"), size=4, radius=4)
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.col("component").alias("component_id"))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _classified(spark, sf_dir, quality, "quality", 0.3)


def op7_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    replaced = pii.replace(table(spark, sf_dir, "documents"), key=PII_KEY)
    return replaced.select("doc_id", "text", "n_entities")


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    packed = packing.pack_documents(table(spark, sf_dir, "documents"))
    return packed.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def op9_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = fingerprints.fingerprints_and_edits(table(spark, sf_dir, "documents"))
    digits = lambda c: F.lower(F.lpad(F.hex(c), 16, "0")).alias
    return found.select("doc_id", "n_chars", "edited_sha256", digits("fp")("fingerprint"), digits("edited_fp")("edited_fingerprint"), "near_edited", "near_next")


def fingerprint_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Block-table search: the fingerprints of every document whose id is divisible by 20 against those of all, at most 3 bits apart."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.coalesce("text", F.lit("")).alias("body"))
    rows = docs.select("doc_id", F.xxhash64("body").alias("h"), "body")
    prints = durable(fingerprints.fingerprints(rows, ["doc_id", "h"], "body").select("doc_id", "fp"), "prints")
    return fingerprints.within(prints.filter("doc_id % 20 = 0"), prints)


def op10_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    tricky = "\\### Assistant: </turn> ok"
    rows = rows.unionByName(spark.createDataFrame([(-7, 0, "user", tricky), (-7, 1, "assistant", tricky)], rows.schema))
    return chat.read_back(chat.conversations(chat.linear(rows))).withColumnRenamed("tree", "conv_id")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_sharding": op1_sharding,
        "sharding_small_limit": sharding_small_limit,
        "op2_suffix_dedup": op2_suffix_dedup,
        "op9_fingerprints": op9_fingerprints,
        "fingerprint_neighbours": fingerprint_neighbours,
        "op10_chat": op10_chat,
        "op3_decontaminate": op3_decontaminate,
        "op4_toxicity": op4_toxicity,
        "op5_simhash_dedup": op5_simhash_dedup,
        "op6_quality": op6_quality,
        "op7_pii": op7_pii,
        "op8_packing": op8_packing,
    }


def _sharding_sql(limit: int, depth: int = 26) -> str:
    """The shortest prefix of each row's bits whose rows fit; enough levels for tables of up to 2**depth shards."""
    return f"""
    WITH d AS (
      SELECT doc_id, octet_length(encode(coalesce(text, ''))) AS n_bytes,
             right(bin(('0x' || substr(md5(coalesce(cast(doc_id AS VARCHAR), 'null')), 1, 8))::BIGINT + 4294967296), 32) AS bits
      FROM documents),
    lv AS (SELECT unnest(range(0, {depth + 1})) AS k),
    b AS (
      SELECT k, left(bits, k) AS shard, count(*) AS shard_rows, sum(n_bytes)::BIGINT AS shard_bytes
      FROM d, lv GROUP BY ALL HAVING sum(n_bytes) <= {limit})
    SELECT doc_id, n_bytes::BIGINT AS n_bytes, shard, shard_rows, shard_bytes, false AS oversized, k::INTEGER AS shard_depth
    FROM (SELECT d.doc_id, d.n_bytes, b.shard, b.k, b.shard_rows, b.shard_bytes, row_number() OVER (PARTITION BY d.doc_id ORDER BY b.k) AS r
          FROM d JOIN lv ON true JOIN b ON b.k = lv.k AND b.shard = left(d.bits, lv.k))
    WHERE r = 1"""


_CHAT_SQL = r"""
    WITH m AS (
      SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
      UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
      UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
    e AS (
      SELECT *, replace(replace(text, '\', '\\'), '</turn>', '\</turn>') AS body FROM m)
    SELECT conv_id, count(*) AS n_turns,
           sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
           coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
           sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
           sum(length(role) + length(body) + 14 + length(text) - length(regexp_replace(text, '#{3,}', '', 'g')))::BIGINT AS formatted_chars
    FROM e GROUP BY conv_id"""


def oracle_sql() -> dict[str, str]:
    return {
        "op1_sharding": _sharding_sql(sharding.LIMIT),
        "sharding_small_limit": _sharding_sql(128 << 10),
        "op10_chat": _CHAT_SQL,
    }
