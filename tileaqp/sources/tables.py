"""Reading and writing: the given tables, text files with a schema, sinks, and made-up uniform tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F, types as T

CORRUPT = "_corrupt"


def load_table(spark: SparkSession, folder: str, name: str, positions: bool = False) -> DataFrame:
    """A Parquet table; ``positions`` adds file and row number, the place of an object in raw data."""
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    return df.select("*", F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("pos")) if positions else df


def _with_corrupt(schema: T.StructType) -> T.StructType:
    return schema if CORRUPT in schema.names else T.StructType([*schema.fields, T.StructField(CORRUPT, T.StringType())])


def load_csv(spark: SparkSession, path: str, schema: T.StructType, header: bool = True) -> DataFrame:
    """Rows that don't fit the schema keep their text in a column of their own."""
    return spark.read.schema(_with_corrupt(schema)).option("header", header).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", CORRUPT).csv(path)


def load_json(spark: SparkSession, path: str, schema: T.StructType) -> DataFrame:
    return spark.read.schema(_with_corrupt(schema)).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", CORRUPT).json(path)


def write_wide_csv(spark: SparkSession, folder: str, path: str) -> DataFrame:
    """Line items with all columns of their order, part, supplier and customer: the same objects in longer rows."""
    t = lambda n: load_table(spark, folder, n)
    wide = wide_rows(spark, folder, t)
    wide.write.option("header", True).option("timestampFormat", "yyyy-MM-dd HH:mm:ss").csv(path)
    return wide


def wide_rows(spark: SparkSession, folder: str, t=None) -> DataFrame:
    t = t or (lambda n: load_table(spark, folder, n))
    l, o, p, s, c = t("lineitem"), t("orders"), t("part"), t("supplier"), t("customer")
    joined = l.join(o, l.l_orderkey == o.o_orderkey, "left").join(p, l.l_partkey == p.p_partkey, "left").join(s, l.l_suppkey == s.s_suppkey, "left")
    return joined.join(c, o.o_custkey == c.c_custkey, "left")


def write_rows(df: DataFrame, path: str, kind: str = "parquet", partition_by: list[str] | None = None) -> None:
    """Results, metrics and round logs as Parquet, CSV or JSON."""
    if kind not in ("parquet", "csv", "json"):
        raise ValueError(f"no sink {kind}")
    w = df.write.partitionBy(*partition_by) if partition_by else df.write
    (w.option("header", True) if kind == "csv" else w).format(kind).save(path)


def with_uniform(df: DataFrame, key: list[str], attrs: int = 10, seed: int = 7, top: float = 1000.0) -> DataFrame:
    """``df`` with ``attrs`` independent doubles in [0, top), from hashes of its key: any part can be made again alone."""
    unit = lambda i: F.xxhash64(*key, F.lit(seed), F.lit(i)).bitwiseAND(F.lit((1 << 53) - 1)) / F.lit(float(1 << 53))
    return df.select("*", *((unit(i) * top).alias(f"a{i}") for i in range(attrs)))


def gen_uniform(spark: SparkSession, rows: int, attrs: int = 10, seed: int = 7, top: float = 1000.0) -> DataFrame:
    """oid and ``attrs`` independent doubles in [0, top)."""
    return with_uniform(spark.range(rows).withColumnRenamed("id", "oid"), ["oid"], attrs, seed, top)
