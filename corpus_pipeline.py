"""A training corpus from raw documents: quality rules, near duplicates, repeated passages, benchmark items, packing.

Each stage takes (spark, docs, sf_dir) and works on all rows its predecessor kept. Rows with a null doc_id can't be
told apart: they pass the stages that compare documents. Null texts fail the quality rules. Extra columns are carried
along whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairlens.llm import decontaminate, minhash_dedup, packing, quality_rules, substring_dedup
from pairlens.llm.queries import tokenizer
from pairlens.llm.shared import Scratch, ship, table


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the fixed limits and the learned decision list keep."""
    return quality_rules.keep_good(docs, quality_rules.learn(docs, table(spark, sf_dir, "labels")))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: the one with the least doc_id."""
    ship(spark)
    out = minhash_dedup.near_duplicates(docs, shingle=5, percent=80)
    return docs.join(out.where(~F.col("kept")).select("doc_id"), "doc_id", "left_anti").select(docs.columns)


def passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without passages that an earlier document has; n_chars counts what is left."""
    ship(spark)
    out = substring_dedup.drop_passages(docs, substring_dedup.repeated_passages(docs))
    return out.withColumn("n_chars", F.coalesce(F.length("text").cast(docs.schema["n_chars"].dataType), F.col("n_chars"))) if "n_chars" in docs.columns else out


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without benchmark items."""
    found = decontaminate.contaminated(docs, table(spark, sf_dir, "benchmark"))
    return docs.join(found.select("doc_id").distinct(), "doc_id", "left_anti").select(docs.columns)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token sequences: one row per piece of a document."""
    ship(spark)
    return packing.pack(docs, tokenizer("byte_bpe_50k.json"))


STAGES = [("quality_rules", quality), ("minhash_near_dedup", near_duplicates), ("substring_dedup", passages), ("benchmark_decontamination", decontamination), ("best_fit_packing", packed)]
#: SQL can't express the learned list, the signatures and the packing; tests hold the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, scratch = table(spark, sf_dir, "documents"), Scratch(spark, "pipeline")
    for name, stage in STAGES[:-1]:
        docs = scratch.keep(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
