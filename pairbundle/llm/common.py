"""What the operators of this subpackage share."""

from __future__ import annotations

import sys
import types

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pairbundle.sources.shared import shared_path, shared_root, staged

__all__ = ["shared_path", "shared_root", "staged", "documents", "doc_text", "text_key", "with_group_facts", "worker_store"]


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def doc_text(docs: DataFrame) -> DataFrame:
    """``doc_id`` and ``text`` alone, null texts as empty ones: other columns, whatever their names, never reach an operator."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))


def text_key(text: Column | str = "text") -> Column:
    """The 32 bytes of a text's SHA-256: rows that share it are taken for rows of equal texts."""
    return F.unhex(F.sha2((F.col(text) if isinstance(text, str) else text).cast("string").cast("binary"), 256))


def with_group_facts(rows: DataFrame, facts: DataFrame, keys: list[str], size: str, share: int = 1024) -> DataFrame:
    """Rows joined with the one row of ``facts`` for their keys, without gathering a large group in one task.

    ``facts`` holds in ``size`` how many rows each group has. Groups of more than a ``share``-th of all rows number fewer than ``share``, so
    these are broadcast whatever the data; the join that shuffles sees only smaller groups. ``rows`` and ``facts`` are written tables."""
    total = facts.agg(F.coalesce(F.sum(size), F.lit(0))).first()[0]
    large = F.col(size) * share > F.lit(total)
    heavy, light = facts.where(large), facts.where(~large)
    out = rows.join(light, keys)
    if heavy.isEmpty():
        return out
    few = F.broadcast(heavy)
    return rows.join(F.broadcast(heavy.select(*keys)), keys, "left_anti").join(light, keys).unionByName(rows.join(few, keys))


def crc_bucket(column: Column, modulus: int) -> Column:
    return F.crc32(column.cast("string").cast("binary")) % modulus


def worker_store() -> dict:
    """A dictionary that lives as long as the Python worker, also across tasks."""
    name = "_pairbundle_worker_store"
    if name not in sys.modules:
        sys.modules[name] = types.ModuleType(name)
        sys.modules[name].data = {}
    return sys.modules[name].data
