"""Readers of the three pair-level layouts, for conversion, and the converter as one command."""

from __future__ import annotations

import sys

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairbundle.operators import convert, layouts
from pairbundle.sources.container import write_container


def write_loose(pairs: DataFrame, path: str) -> None:
    """A file for each modality of each sample. One at a time by each task, through the store's own interface."""
    from pairbundle.sources.container import filesystem

    def put(batches):
        store, base = filesystem(path)
        store.create_dir(base, recursive=True)
        for b in batches:
            for name, content in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                with store.open_output_stream(f"{base}/{name}") as f:
                    f.write(content)
            yield b.select(["path"])

    layouts.loose(pairs).mapInArrow(put, "path string").count()


def write_path_table(found: DataFrame, path: str) -> None:
    """Texts as JSON lines with media paths, media as files."""
    from pairbundle.sources.container import filesystem

    texts, media = layouts.path_table(found)
    texts.write.json(f"{path}/texts")

    def put(batches):
        store, base = filesystem(path)
        store.create_dir(f"{base}/media", recursive=True)
        for b in batches:
            for name, content in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                with store.open_output_stream(f"{base}/{name}") as f:
                    f.write(content)
            yield b.select(["path"])

    media.mapInArrow(put, "path string").count()


def write_pair_record(pairs: DataFrame, path: str) -> None:
    """A record for each pair, sorted by id."""
    layouts.pair_record(pairs).repartitionByRange("sample_id").sortWithinPartitions("sample_id").write.parquet(path)


def read_pairs(spark: SparkSession, path: str, layout: str) -> DataFrame:
    """pair_ord, media (bytes, of any kind), text, src_id from any of the layouts."""
    if layout == "loose":
        files = spark.read.format("binaryFile").option("pathGlobFilter", "*.*").load(path).select(F.regexp_extract("path", r"([0-9]+)\.(media|text)$", 1).cast("long").alias("pair_ord"), F.regexp_extract("path", r"\.(media|text)$", 1).alias("side"), "content")
        media, text = (files.where(F.col("side") == s).select("pair_ord", F.col("content").alias(s)) for s in ("media", "text"))
        return media.join(text, "pair_ord", "left").select("pair_ord", "media", F.decode("text", "UTF-8").alias("text"), F.col("pair_ord").alias("src_id"))
    if layout == "path_table":
        texts = spark.read.schema("sample_id long, path string, text string, _corrupt string").option("columnNameOfCorruptRecord", "_corrupt").json(f"{path}/texts").where("_corrupt IS NULL")
        media = spark.read.format("binaryFile").load(f"{path}/media").select(F.concat(F.lit("media/"), F.regexp_extract("path", r"([0-9]+)$", 1)).alias("path"), F.col("content").alias("media"))
        return texts.join(media, "path").select(F.col("sample_id").alias("pair_ord"), "media", "text", F.col("sample_id").alias("src_id"))
    if layout == "pair_record":
        number = lambda b: F.conv(F.hex(b), 16, 10).cast("int")
        rows = spark.read.parquet(path).withColumn("m", number(F.substring("record", 1, 4)))
        media = F.expr("substring(record, 5, m)")
        return rows.select(F.col("sample_id").alias("pair_ord"), media.alias("media"), F.expr("decode(substring(record, 9 + m, octet_length(record)), 'UTF-8')").alias("text"), F.col("sample_id").alias("src_id"))
    raise ValueError(f"no such layout: {layout}")


def run_conversion(spark: SparkSession, src: str, layout: str, dest: str, **options) -> dict:
    """From a layout on storage to a container, in one call; returns the container's header."""
    from pairbundle.sources.container import read_header

    write_container(convert.bundles(read_pairs(spark, src, layout), **options), dest)
    return read_header(dest)


if __name__ == "__main__":
    print(run_conversion(SparkSession.builder.getOrCreate(), *sys.argv[1:4]))
