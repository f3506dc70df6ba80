"""The four layouts: what each writes, and what an access touches in each."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def loose(pairs: DataFrame) -> DataFrame:
    """A file for each modality of each sample: path and content. ``pairs`` has sample_id, media, text."""
    stem = F.lpad(F.col("sample_id").cast("string"), 12, "0")
    rows = F.array(F.struct(F.concat(stem, F.lit(".media")).alias("path"), F.col("media").cast("binary").alias("content")), F.struct(F.concat(stem, F.lit(".text")).alias("path"), F.col("text").cast("binary").alias("content")))
    return pairs.select(F.explode(rows).alias("f")).select("f.path", "f.content").where("content IS NOT NULL")


def path_table(found: DataFrame) -> tuple[DataFrame, DataFrame]:
    """A table of texts with media paths, and a file for each media object. ``found`` are whole bundles."""
    path = F.concat(F.lit("media/"), F.lpad(F.col("bundle_id").cast("string"), 12, "0"))
    texts = found.select(path.alias("path"), "start_idx", F.posexplode("texts").alias("pos", "t")).select((F.col("start_idx") + F.col("pos")).alias("sample_id"), "path", "t.text")
    return texts, found.select(path.alias("path"), F.col("media").cast("binary").alias("content"))


def pair_record(pairs: DataFrame) -> DataFrame:
    """A record for each pair, in order of ids: sample_id, record. Its offsets are the running sum of its lengths."""
    media, text = F.col("media").cast("binary"), F.coalesce("text", F.lit("")).cast("binary")
    head = lambda b: F.unhex(F.lpad(F.hex(F.octet_length(b)), 8, "0"))
    return pairs.select("sample_id", F.concat(head(media), media, head(text), text).alias("record"))


def write_bundles(found: DataFrame, path: str, bundles_per_file: int = 100_000) -> None:
    """Bundles as Parquet, in order of their ids and in files of bounded size: ranges of start_idx and end_idx don't overlap, so that
    statistics prune, and texts are read without media."""
    found.repartitionByRange("bundle_id").sortWithinPartitions("bundle_id").write.option("maxRecordsPerFile", bundles_per_file).parquet(path)


def explode_to(found: DataFrame, layout: str):
    """Bundles back to a baseline."""
    from pairbundle.operators.convert import as_pairs

    return {"loose": lambda: loose(as_pairs(found)), "path_table": lambda: path_table(found), "pair_record": lambda: pair_record(as_pairs(found)), "bundle": lambda: found}[layout]()


def stats(corpora: dict[str, DataFrame]) -> DataFrame:
    """One row for each corpus (name -> clusters): kind, counts and bytes from one aggregation each."""
    from pairbundle.operators.addressing import encoded_length
    from pairbundle.operators.convert import kind_of

    out = None
    for name, found in corpora.items():
        n = F.col("n_texts")
        one = found.agg(F.min("n_texts").alias("least"), F.max("n_texts").alias("most"), F.sum("n_texts").alias("n_texts"), F.count("*").alias("n_bundles"), F.sum("media_bytes").alias("media_bytes"), F.sum("text_bytes").alias("text_bytes"), F.sum(F.greatest(n, F.lit(1)) * F.col("media_bytes")).alias("dup_bytes"), F.sum(encoded_length()).alias("body_bytes"), F.sum(F.greatest(n, F.lit(1)) * encoded_length()).alias("touched_bytes"))
        kind = kind_of(F.col("least"), F.col("most"))
        row = one.select(F.lit(name).alias("corpus"), kind.alias("kind"), F.when(F.col("most") == 0, F.col("n_bundles")).otherwise(F.col("n_texts")).alias("n_pairs"), "n_bundles", "media_bytes", "text_bytes", "dup_bytes", "body_bytes", "touched_bytes")
        out = row if out is None else out.union(row)
    return out


def per_layout(df: DataFrame, values: dict[str, dict[str, Column]]) -> DataFrame:
    """A row for each layout with the given columns."""
    rows = F.array(*[F.struct(F.lit(layout).alias("layout"), *[c.alias(n) for n, c in columns.items()]) for layout, columns in values.items()])
    return df.withColumn("_l", F.explode(rows)).select(*df.columns, "_l.*")
