"""Numbers, ranges and offsets without a global window: range partitions, their totals, and sums inside each partition."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pairbundle.model import LIST_FRAME, MEDIA_FRAME, TEXT_FRAME
from pairbundle.sources.shared import staged


def prefix_sum(df: DataFrame, order: list[str], sums: dict[str, Column | str], mode: str = "distributed") -> DataFrame:
    """Adds an exclusive running sum for each entry of ``sums`` (name -> value), in the given total order.

    The range-partitioned rows are written once, so that totals and sums see the same partitions; only one total for each partition
    meets in one place. ``mode='window'`` is the form for small tables: one window over all rows."""
    before = lambda w: w.rowsBetween(Window.unboundedPreceding, -1)
    values = {f"_v{k}": F.expr(v) if isinstance(v, str) else v for k, v in enumerate(sums.values())}
    if mode == "window":
        w = before(Window.orderBy(*order))
        out = df.withColumns(values)
        return out.withColumns({n: F.coalesce(F.sum(v).over(w), F.lit(0)).cast("long") for n, v in zip(sums, values)}).drop(*values)
    ranged = staged(df.withColumns(values).repartitionByRange(*order).withColumn("_part", F.spark_partition_id()), "ranged")
    totals = ranged.groupBy("_part").agg(*[F.sum(v).alias(v) for v in values])
    over = before(Window.orderBy("_part"))
    bases = totals.select("_part", *[F.coalesce(F.sum(v).over(over), F.lit(0)).alias(f"_b{v}") for v in values])
    inside = before(Window.partitionBy("_part").orderBy(*order))
    local = ranged.withColumns({f"_s{v}": F.coalesce(F.sum(v).over(inside), F.lit(0)) for v in values})
    out = local.join(bases, "_part")
    return out.withColumns({n: (F.col(f"_s{v}") + F.col(f"_b{v}")).cast("long") for n, v in zip(sums, values)}).select(*df.columns, *sums)


def dense_ids(df: DataFrame, order: list[str], name: str = "id", mode: str = "distributed") -> DataFrame:
    """0-based numbers in the given total order."""
    return prefix_sum(df, order, {name: F.lit(1)}, mode)


def encoded_length(media_bytes: Column | str = "media_bytes", text_bytes: Column | str = "text_bytes", n_texts: Column | str = "n_texts") -> Column:
    """Bytes of an encoded bundle, exactly those that the container's encoder writes."""
    of = lambda c: F.col(c) if isinstance(c, str) else c
    return (F.lit(MEDIA_FRAME + LIST_FRAME) + of(media_bytes) + of(text_bytes) + F.lit(TEXT_FRAME) * of(n_texts)).cast("long")


def number(clusters: DataFrame, order: str = "first_seen", mode: str = "distributed") -> DataFrame:
    """bundle_id, start_idx, end_idx, byte_offset and byte_len of bundles (fingerprint, media_bytes, rep_ord, n_texts, text_bytes).

    A bundle of a uni-modal corpus owns one id; otherwise a bundle without texts owns none, and its end lies before its start."""
    uni = clusters.agg(F.coalesce(F.max("n_texts"), F.lit(0))).first()[0] == 0
    owned = F.lit(1) if uni else F.col("n_texts")
    keys = ["rep_ord", "fingerprint"] if order == "first_seen" else ["fingerprint", "media_bytes"]
    sized = clusters.withColumn("byte_len", encoded_length())
    out = prefix_sum(sized, keys, {"bundle_id": F.lit(1), "start_idx": owned, "byte_offset": F.col("byte_len")}, mode)
    return out.withColumn("end_idx", (F.col("start_idx") + owned - 1).cast("long"))


def shard(bundles: DataFrame, target_bytes: int) -> DataFrame:
    """shard_id and local_offset: a shard begins with the first bundle at or after each multiple of the target."""
    cut = bundles.withColumn("shard_id", F.floor(F.col("byte_offset") / F.lit(target_bytes)).cast("long"))
    first = cut.groupBy("shard_id").agg(F.min("byte_offset").alias("_first"))
    return cut.join(first, "shard_id").withColumn("local_offset", F.col("byte_offset") - F.col("_first")).drop("_first")
