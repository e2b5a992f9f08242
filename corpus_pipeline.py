"""A training corpus from ``documents``: keep good texts once, without benchmark passages and personal data, packed.

Every stage takes (spark, docs, sf_dir), works on all rows of ``docs`` and returns a
DataFrame; all but the last return the columns of ``documents``. Their results are
written as Parquet and read again in between.

1. quality: documents with a score below 0.3 go.
2. near duplicates: of each group linked by SimHash fingerprints at most four bits apart, or by a
   five-word shingle similarity of 0.8 or more, the row with the smallest id stays (one without an id
   only if none has one). Pigeonring finds the links of fingerprints; the shingles find the rest.
3. decontamination: documents with a benchmark window of ten words go.
4. personal data: entities become surrogates; n_chars is counted anew.
5. packing: a row per piece with its sequence.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from tileaqp.llm import decontaminate, packing, pii, quality, simhash_dedup
from tileaqp.llm.queries import PII_KEY, table
from tileaqp.runtime import durable

MIN_QUALITY = 0.3


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = quality.fit(docs.select("doc_id", "text"), table(spark, sf_dir, "labels"), "quality")
    return quality.score(docs, model, column="_score").filter(F.col("_score") >= MIN_QUALITY).select(docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row stays of each group. A row is named by id and text, so rows may repeat an id or have none."""
    text = F.coalesce(F.sha2(F.col("text").cast("string"), 256), F.lit(""))
    named = docs.select(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", text.alias("digest")).alias("row"), "text")
    found = simhash_dedup.near_duplicates(named, key="row", radius=simhash_dedup.RADIUS)
    kept = found.filter(F.col("row").eqNullSafe(F.col("component"))).select(F.col("row.doc_id").alias("_id"), F.col("row.digest").alias("_digest"))
    kept = durable(kept.groupBy("_id", "_digest").agg(F.count("*").alias("_times")), "kept")
    out = docs.withColumn("_own", text).join(kept, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_own") == F.col("_digest")))
    order = Window.partitionBy("_id", "_digest").orderBy(*docs.columns)
    one = out.filter("_times > 1").withColumn("_n", F.row_number().over(order)).filter("_n = 1").select(docs.columns)
    return out.filter("_times = 1").select(docs.columns).unionByName(one)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.find(docs, table(spark, sf_dir, "benchmark")).filter("n_hit = 0").select(docs.columns)


def replace_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = pii.replace(docs, key=PII_KEY, count=None)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)).select(docs.columns) if "n_chars" in docs.columns else out.select(docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    packed = packing.pack_documents(docs.select("doc_id", "text"))
    return packed.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


STAGES = [
    ("quality", keep_quality),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("personal_data", replace_personal_data),
    ("packing", pack),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = durable(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)


#: Classifier, sketches and tokens have no SQL form; tests compare with brute force.
ORACLE_SQL = None
