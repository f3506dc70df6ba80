"""Epochs: permutations of the sample ids and the training strategies on bundles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pairbundle.operators.addressing import dense_ids


def order_key(seed: int, epoch: int, column: str = "sample_id") -> Column:
    """The md5 that orders an epoch; equal in any engine."""
    return F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit(str(epoch)), F.col(column).cast("string")))


def permute(ids: DataFrame, epoch: int = 0, seed: int = 42, mode: str = "distributed") -> DataFrame:
    """sample_id and its step in the epoch: each id once, in an order that seed and epoch alone decide."""
    return dense_ids(ids.select("sample_id").withColumn("_key", order_key(seed, epoch)), ["_key", "sample_id"], "step", mode).select("step", "sample_id")


def sample_ids(index: DataFrame) -> DataFrame:
    """All ids with their bundles: sample_id, bundle_id, text_pos."""
    each = index.where("end_idx >= start_idx").select("bundle_id", "start_idx", F.explode(F.sequence("start_idx", "end_idx")).alias("sample_id"))
    return each.select("sample_id", "bundle_id", (F.col("sample_id") - F.col("start_idx")).alias("text_pos"))


def epoch_all(index: DataFrame, epoch: int = 0, seed: int = 42, mode: str = "distributed") -> DataFrame:
    """Every pair once: step, sample_id, bundle_id, text_pos."""
    ids = sample_ids(index)
    return permute(ids, epoch, seed, mode).join(ids, "sample_id").select("step", "sample_id", "bundle_id", "text_pos")


def epoch_one(index: DataFrame, epoch: int = 0, seed: int = 42) -> DataFrame:
    """One text of each bundle, picked by hash: bundle_id, text_pos, sample_id."""
    word = F.conv(F.substring(order_key(seed, epoch, "bundle_id"), 1, 8), 16, 10).cast("long")
    owned = index.where("end_idx >= start_idx").withColumn("text_pos", F.pmod(word, F.col("end_idx") - F.col("start_idx") + 1))
    return owned.select("bundle_id", "text_pos", (F.col("start_idx") + F.col("text_pos")).alias("sample_id"))


def epoch_concat(found: DataFrame, separator: str = " ", max_texts: int | None = None, max_chars: int | None = None) -> DataFrame:
    """All texts of each bundle as one sequence; if given, only the first ``max_texts`` of them, or the first ``max_chars`` characters."""
    texts = F.col("texts") if max_texts is None else F.slice("texts", 1, max_texts)
    joined = F.array_join(F.transform(texts, lambda t: t["text"]), separator)
    sequence = joined if max_chars is None else F.substring(joined, 1, max_chars)
    return found.where("n_texts > 0").select("bundle_id", sequence.alias("sequence"))


def batches(epoch: DataFrame, batch_size: int, workers: int = 1, drop_last: bool = False, total: int | None = None) -> DataFrame:
    """Adds worker, batch_no and slot: steps go round the workers batch by batch."""
    n = F.lit(batch_size)
    out = epoch.withColumn("batch_no", F.floor(F.col("step") / n).cast("long")).withColumn("slot", F.pmod("step", n).cast("int")).withColumn("worker", F.pmod("batch_no", F.lit(workers)).cast("int"))
    if drop_last:
        total = total if total is not None else epoch.count()
        out = out.where(F.col("batch_no") < total // batch_size)
    return out


def stream_shuffle(ids: DataFrame, shard_of: Column, epoch: int = 0, seed: int = 42, buffer: int = 64) -> DataFrame:
    """What a sequential format can do: shards in hashed order, then a bounded shuffle. Within each shard, runs of ``buffer`` ids are
    permuted. A window runs over one shard at a time."""
    shard_key = F.md5(F.concat_ws("|", F.lit(f"{seed}|{epoch}|shard"), F.col("shard").cast("string")))
    rows = ids.select("sample_id", shard_of.cast("long").alias("shard"))
    place = F.row_number().over(Window.partitionBy("shard").orderBy("sample_id")) - 1
    return rows.withColumn("_shard", shard_key).withColumn("run", F.floor(place / buffer)).withColumn("_key", order_key(seed, epoch)).select("sample_id", "shard", "_shard", "run", "_key")


def randomness(stream: DataFrame, mode: str = "distributed") -> DataFrame:
    """Mean displacement of ids in a stream, as a share of the one third that a full permutation has."""
    placed = dense_ids(stream, ["_shard", "run", "_key", "sample_id"], "step", mode)
    return placed.agg(F.count("*").alias("n"), F.avg(F.abs(F.col("step") - F.col("sample_id"))).alias("displacement")).select("n", "displacement", (F.col("displacement") / (F.col("n") / 3)).alias("share"))
