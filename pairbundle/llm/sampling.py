"""Bounded, deterministic samples of labelled rows for fitting classifiers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairbundle.llm.common import crc_bucket, doc_text, staged


def held_out(modulus: int, remainder: int):
    """Whether a row's labels may not be learnt from: the crc32 of its doc_id as text decides. A null doc_id is never held out."""
    return F.coalesce(crc_bucket(F.col("doc_id"), modulus) == remainder, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, label: str, modulus: int, remainder: int, most: int) -> DataFrame:
    """doc_id, text, y of at most ``most`` labelled rows outside the held-out share: those with the least md5 of their doc_id, so that
    the choice depends on no order or partition. The sample's ids are bounded by ``most`` and therefore broadcast. Copies of a text
    count once, with their largest label."""
    chosen = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).where("doc_id IS NOT NULL AND y IS NOT NULL")
    chosen = chosen.where(~held_out(modulus, remainder)).groupBy("doc_id").agg(F.max("y").alias("y"))
    chosen = chosen.orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id").limit(most)
    rows = doc_text(docs).join(F.broadcast(chosen), "doc_id")
    return staged(rows.groupBy("text").agg(F.min("doc_id").alias("doc_id"), F.max("y").alias("y")), f"sample-{label}", narrow=True)


def labels_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")
