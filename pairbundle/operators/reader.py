"""Retrieval of pairs from bundles."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairbundle.operators import locate as loc


def get(bundles: DataFrame, sample_id: int) -> DataFrame:
    """One pair: the bundle whose range holds the id, found by predicates that reach the scan, and the text at its place."""
    hit = bundles.where((F.col("start_idx") <= sample_id) & (F.col("end_idx") >= sample_id))
    return hit.select(F.lit(sample_id).cast("long").alias("sample_id"), "bundle_id", "media", F.get("texts", (F.lit(sample_id) - F.col("start_idx")).cast("int"))["text"].alias("text"))


def get_many(requests: DataFrame, bundles: DataFrame, header: dict, ordered: bool = False, **options) -> DataFrame:
    """Pairs for a batch of requests (sample_id, and step if ordered). Requests are grouped by bundle, so a bundle is read once."""
    found = loc.locate(requests.select("sample_id").distinct(), bundles, header, **options).groupBy("bundle_id").agg(F.collect_list(F.struct("sample_id", "text_pos")).alias("asked"))
    read = found.join(bundles.select("bundle_id", "media", "texts"), "bundle_id")
    pairs = read.select("bundle_id", "media", "texts", F.explode("asked").alias("a")).select("a.sample_id", "bundle_id", "media", F.get("texts", F.col("a.text_pos").cast("int"))["text"].alias("text"))
    out = requests.join(pairs, "sample_id")
    return out.orderBy("step") if ordered else out


def iter_batches(pairs: DataFrame, batch_size: int = 64) -> Iterator[list[dict]]:
    """A loader's bridge: rows in their order, one partition at a time on the driver, as lists of dictionaries."""
    held: list[dict] = []
    for row in pairs.toLocalIterator(prefetchPartitions=True):
        held.append(row.asDict())
        if len(held) == batch_size:
            yield held
            held = []
    if held:
        yield held
