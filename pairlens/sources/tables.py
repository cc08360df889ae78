"""Readers and writers of pairs, and the SQL surface."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

PAIR = "pair_id BIGINT, split STRING, lang STRING, origin STRING, seq BIGINT, reference STRING, summary STRING"


def read_pairs(spark: SparkSession, path: str, form: str = "json", schema: str = PAIR, **options) -> DataFrame:
    """json lines, csv, orc or parquet with a declared schema; broken lines keep their text in _corrupt_record."""
    if form in ("json", "csv"):
        return spark.read.schema(f"{schema}, _corrupt_record STRING").option("mode", "PERMISSIVE").options(**options).format(form).load(path)
    return spark.read.schema(schema).format(form).load(path)


def read_bytes(spark: SparkSession, path: str) -> DataFrame:
    """Whole files with whether they are valid UTF-8, for an audit of encodings."""
    return spark.read.format("binaryFile").load(path).select("path", "length", F.expr("is_valid_utf8(content)").alias("valid"), F.col("content"))


def write_labelled(labelled: DataFrame, path: str, rows_per_file: int = 1_000_000) -> None:
    labelled.repartition("split", "verdict", F.pmod(F.xxhash64("pair_id"), F.lit(8))).write.mode("overwrite").option("maxRecordsPerFile", rows_per_file).partitionBy("split", "verdict").parquet(path)


def write_bucketed(pairs: DataFrame, table: str, buckets: int, key: str = "pair_id") -> None:
    """Joins on the key of two such tables need no exchange."""
    pairs.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def register(spark: SparkSession, pairs: DataFrame, name: str = "pairs") -> None:
    """The pairs as a view; the checks, the R-1 score and the table functions as SQL functions of the session."""
    from pairlens.functions.tables import register_tables
    from pairlens.functions.udfs import rouge1_f

    spark.udf.register("rouge_f", rouge1_f)
    register_tables(spark)
    pairs.createOrReplaceTempView(name)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION compression_ratio(r STRING, s STRING) RETURNS DOUBLE RETURN try_divide(CAST(length(r) AS DOUBLE), length(s))")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION sieve_verdict(r STRING, s STRING) RETURNS STRING RETURN CASE WHEN r IS NULL OR s IS NULL OR length(r) = 0 OR length(s) = 0 THEN 'empty' WHEN length(r) < 50 THEN 'ref_short' "
        "WHEN length(s) < 20 THEN 'summ_short' WHEN r = s THEN 'identical' WHEN length(r) < length(s) * 1.25D THEN 'low_cr' WHEN contains(r, s) THEN 'extractive' ELSE 'valid' END"
    )
