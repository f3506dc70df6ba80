"""Comparisons between layouts: ratios, speed-ups, averages, crossovers, ablation and the issue matrix."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def normalize(rows: DataFrame, value: str, to: str, keys: tuple[str, ...] = ("corpus",)) -> DataFrame:
    """Adds ``normalized``: the value over that of layout ``to``."""
    base = rows.where(F.col("layout") == to).select(*keys, F.col(value).alias("_base"))
    return rows.join(base, list(keys)).withColumn("normalized", F.col(value) / F.col("_base")).drop("_base")


def vs_best(rows: DataFrame, value: str = "rate", ours: str = "bundle", keys: tuple[str, ...] = ("corpus",), larger_is_better: bool = True) -> DataFrame:
    """Our value over that of the best baseline."""
    pick = F.max if larger_is_better else F.min
    own, rest = F.when(F.col("layout") == ours, F.col(value)), F.when(F.col("layout") != ours, F.col(value))
    return rows.groupBy(*keys).agg(F.max(own).alias("ours"), pick(rest).alias("best_baseline")).withColumn("speedup", F.col("ours") / F.col("best_baseline") if larger_is_better else F.col("best_baseline") / F.col("ours"))


def means(rates: DataFrame, keys: tuple[str, ...] = ("corpus", "layout")) -> DataFrame:
    """The averages over a sweep of capacities that a reader may mean: of rates, and the rate of the mean time."""
    return rates.groupBy(*keys).agg(F.avg("rate").alias("mean_of_rates"), (1 / F.avg(1 / F.col("rate"))).alias("rate_of_mean_time"))


def mean_ratio(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """Mean of a over b, and mean of the reduction from a to b: two different averages."""
    return pairs.agg(F.avg(F.col(a) / F.col(b)).alias("mean_ratio"), F.avg(1 - F.col(b) / F.col(a)).alias("mean_reduction"))


def crossover(rates: DataFrame, rising: str = "path_table", flat: str = "pair_record") -> DataFrame:
    """The least cache share at which one layout reaches another."""
    wide = rates.groupBy("corpus", "share").agg(F.max(F.when(F.col("layout") == rising, F.col("rate"))).alias("a"), F.max(F.when(F.col("layout") == flat, F.col("rate"))).alias("b"))
    return wide.groupBy("corpus").agg(F.min(F.when(F.col("a") >= F.col("b"), F.col("share"))).alias("share"))


def ablation(full: DataFrame, no_cache: DataFrame) -> DataFrame:
    """Drop of the rate without a cache, and then without the format: full and no_cache are rates by corpus, layout and share."""
    mean = lambda df, layout, name: df.where(F.col("layout") == layout).groupBy("corpus").agg(F.avg("rate").alias(name))
    rows = mean(full, "bundle", "full").join(mean(no_cache, "bundle", "no_cache"), "corpus").join(mean(no_cache, "loose", "no_format"), "corpus")
    return rows.withColumn("drop_no_cache", 1 - F.col("no_cache") / F.col("full")).withColumn("drop_no_format", 1 - F.col("no_format") / F.col("no_cache"))


def issue_matrix(rows: DataFrame, redundant: float = 1.5, many_files: int = 2, heavy_index: float = 4.0) -> DataFrame:
    """Whether a layout has each problem, by thresholds of ours: rows have layout, media_written, media_bytes, files, shares (whether
    accesses share objects under a stable key), index_bytes and bundle_index_bytes."""
    return rows.select("corpus", "layout", (F.col("media_written") > redundant * F.col("media_bytes")).alias("redundancy"), (F.col("files") > many_files).alias("small_files"), (~F.col("shares")).alias("cache_unfriendly"), (F.col("index_bytes") > heavy_index * F.col("bundle_index_bytes")).alias("heavy_index"))
