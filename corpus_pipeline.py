"""A training-data pipeline of five stages over ``documents``: each stage gets what its predecessor kept, written and read again.

Every stage takes (spark, docs, sf_dir); all but the last return the columns of documents. Stages on texts decide by doc_id and a hash of
the text together, so rows that share a doc_id are judged each on its own text; repeated rows leave one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pairbundle.llm.common import documents, staged, text_key
from pairbundle.llm.exact_dedup import exact_groups
from pairbundle.llm.mixing import mixed_documents
from pairbundle.llm.packing import packed_documents
from pairbundle.llm.sampling import labels_of
from pairbundle.llm.simhash import labelled_rows
from pairbundle.llm.toxicity import toxic_rows


def without_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose calibrated toxicity is below one half."""
    return toxic_rows(docs, labels_of(spark, sf_dir), keep=True)


def without_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, the row with the largest doc_id."""
    return _only(docs, exact_groups(docs).where("kept"))


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of a component of linked fingerprints, the row with the least doc_id, null ids last; of such rows, the one with the least text_key."""
    rows = labelled_rows(docs).groupBy("label", "doc_id", "text_key").agg(F.count("*").alias("n"))
    first = F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "text_key", "n")).alias("first")
    return _only(docs, rows.groupBy("label").agg(first).select("first.doc_id", "first.text_key", "first.n"), F.col("n"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document at least once; sources with small shares again, so that none is seen over 1.25 times as often as another."""
    return mixed_documents(docs, repetition=1.25)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The places of all pieces in sequences."""
    return packed_documents(docs)


def _only(docs: DataFrame, kept: DataFrame, n: Column | None = None) -> DataFrame:
    """One row for each doc_id and text_key of ``kept``; null counts as an id. A row of ``kept`` stands for ``n`` rows, or one."""
    keys = kept.select(F.col("doc_id").alias("_pb_id"), F.col("text_key").alias("_pb_key"), (F.lit(1) if n is None else n).alias("_pb_n")).groupBy("_pb_id", "_pb_key").agg(F.sum("_pb_n").alias("_pb_n"))
    keys = staged(keys, "kept", narrow=True)
    own = text_key(F.coalesce(F.col("text").cast("string"), F.lit("")))
    match = F.col("doc_id").cast("long").eqNullSafe(F.col("_pb_id")) & (own == F.col("_pb_key"))
    rows = docs.join(keys, match, "left_semi")
    if keys.where("_pb_n > 1").isEmpty():
        return rows
    return rows.withColumn("_pb_own", own).dropDuplicates(["doc_id", "_pb_own"]).drop("_pb_own")


STAGES = [("toxicity", without_toxic), ("exact_dedup", without_copies), ("near_dedup", without_near_copies), ("mixing", mixed), ("packing", packed)]

#: Toxicity and SimHash have no SQL form; tests hold the rows against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
