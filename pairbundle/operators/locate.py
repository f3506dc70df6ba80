"""The adaptive locator: sample_id -> bundle_id, text_pos, byte_offset, byte_len.

``requests`` has sample_id, ``index`` has bundle_id, start_idx, end_idx, byte_offset, byte_len. Ids outside all ranges, and null ids,
give no row; ``how='left'`` gives nulls for them, ``strict`` raises.
"""

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pairbundle.model import FIXED, HYBRID
from pairbundle.operators.convert import classify  # noqa: F401  (the header's kind)

COLUMNS = ("sample_id", "bundle_id", "text_pos", "byte_offset", "byte_len")

#: Up to so many bundles, starts go to executors as sorted arrays: 24 bytes each, 48 MB.
BROADCAST_BUNDLES = 2_000_000


def direct(requests: DataFrame, index: DataFrame, how: str = "inner") -> DataFrame:
    """One text or none for each media object: the id is the bundle."""
    return _by_bundle(requests.withColumn("bundle_id", F.col("sample_id")).withColumn("text_pos", F.lit(0).cast("long")), index, how)


def ratio(requests: DataFrame, index: DataFrame, texts_each: int, how: str = "inner") -> DataFrame:
    """A fixed number of texts for each media object: division and remainder."""
    r = F.lit(texts_each)
    wanted = requests.withColumn("bundle_id", F.floor(F.col("sample_id") / r).cast("long")).withColumn("text_pos", F.pmod("sample_id", r).cast("long"))
    return _by_bundle(wanted, index, how)


def _by_bundle(wanted: DataFrame, index: DataFrame, how: str) -> DataFrame:
    return wanted.join(index.select("bundle_id", "byte_offset", "byte_len"), "bundle_id", how).select(*COLUMNS)


def hashed(requests: DataFrame, index: DataFrame, how: str = "inner") -> DataFrame:
    """An entry for every id, as a hash table would hold: for comparison."""
    entries = index.where("end_idx >= start_idx").select("bundle_id", "start_idx", "byte_offset", "byte_len", F.explode(F.sequence("start_idx", "end_idx")).alias("sample_id"))
    return requests.join(entries, "sample_id", how).withColumn("text_pos", F.col("sample_id") - F.col("start_idx")).select(*COLUMNS)


def pair_array(requests: DataFrame, n_pairs: int) -> DataFrame:
    """The pair-record layout's array: the record's number is the id."""
    return requests.where(F.col("sample_id").between(0, n_pairs - 1)).select("sample_id", F.col("sample_id").alias("record_id"))


def range_theta(requests: DataFrame, index: DataFrame, how: str = "inner") -> DataFrame:
    """The range condition as it stands, a nested loop: reference for small tables only."""
    i = index.where("end_idx >= start_idx")
    return requests.join(i, requests["sample_id"].between(i["start_idx"], i["end_idx"]), how).withColumn("text_pos", F.col("sample_id") - F.col("start_idx")).select(*COLUMNS)


def range_binned(requests: DataFrame, index: DataFrame, width: int = 16, how: str = "inner") -> DataFrame:
    """Ranges and ids meet in bins of ids; the condition decides. Two shuffles or one broadcast."""
    bins = F.sequence(F.floor(F.col("start_idx") / width), F.floor(F.col("end_idx") / width))
    cells = index.where("end_idx >= start_idx").withColumn("_bin", F.explode(bins))
    r = requests.withColumn("_bin", F.floor(F.col("sample_id") / width))
    met = r.join(cells, (r["_bin"] == cells["_bin"]) & r["sample_id"].between(cells["start_idx"], cells["end_idx"]), how)
    return met.withColumn("text_pos", F.col("sample_id") - F.col("start_idx")).select(*COLUMNS)


def range_asof(requests: DataFrame, index: DataFrame, cells: int = 256) -> DataFrame:
    """Ranges and ids in one order; each id takes the last range before it. Ids are dealt by stretches of the id space, and a range
    also goes, once, to each later stretch it reaches into, so no row needs another partition."""
    i = index.where("end_idx >= start_idx")
    top = i.agg(F.max("end_idx")).first()[0]
    step = max(1, -(-((top or 0) + 1) // cells))
    entry = F.struct("bundle_id", "start_idx", "end_idx", "byte_offset", "byte_len").alias("entry")
    cell = lambda c: F.floor(F.col(c) / step)
    ranges = i.select(F.explode(F.sequence(cell("start_idx"), cell("end_idx"))).alias("cell"), F.col("start_idx").alias("at"), F.lit(0).alias("turn"), entry, F.lit(None).cast("long").alias("sample_id"))
    asked = requests.where("sample_id IS NOT NULL").select(cell("sample_id").alias("cell"), F.col("sample_id").alias("at"), F.lit(1).alias("turn"), F.lit(None).cast(ranges.schema["entry"].dataType).alias("entry"), "sample_id")
    w = Window.partitionBy("cell").orderBy("at", "turn").rowsBetween(Window.unboundedPreceding, 0)
    met = ranges.unionByName(asked).withColumn("entry", F.last("entry", ignorenulls=True).over(w)).where("turn = 1 AND sample_id <= entry.end_idx")
    return met.select("sample_id", "entry.bundle_id", (F.col("sample_id") - F.col("entry.start_idx")).alias("text_pos"), "entry.byte_offset", "entry.byte_len")


def range_search(requests: DataFrame, index: DataFrame, most: int = BROADCAST_BUNDLES) -> DataFrame:
    """Binary search in the sorted starts, sent to the executors once; behind a check of their number, else by stretches."""
    owned = index.where("end_idx >= start_idx").select("start_idx", "end_idx", "bundle_id")
    if owned.count() > most:
        return range_asof(requests, index)
    arrow = owned.orderBy("start_idx").toArrow()
    starts, ends, ids = (arrow.column(k).to_numpy() for k in range(3))
    held = requests.sparkSession.sparkContext.broadcast((starts, ends, ids))

    @F.pandas_udf("bundle_id long, text_pos long")
    def search(sample: pd.Series) -> pd.DataFrame:
        s, e, b = held.value
        x = sample.to_numpy(dtype=np.float64, na_value=-1).astype(np.int64)
        if not len(s):
            return pd.DataFrame({"bundle_id": pd.array([None] * len(x), "Int64"), "text_pos": pd.array([None] * len(x), "Int64")})
        k = np.searchsorted(s, x, side="right") - 1
        ok = (k >= 0) & (x <= e[np.maximum(k, 0)])
        k = np.maximum(k, 0)
        return pd.DataFrame({"bundle_id": pd.Series(b[k]).astype("Int64").where(pd.Series(ok)), "text_pos": pd.Series(x - s[k]).astype("Int64").where(pd.Series(ok))})

    found = requests.withColumn("hit", search("sample_id")).select("sample_id", "hit.bundle_id", "hit.text_pos").where("bundle_id IS NOT NULL")
    return _by_bundle(found, index, "inner")


def range_cogroup(requests: DataFrame, index: DataFrame, cells: int = 256) -> DataFrame:
    """Each stretch of the id space meets the slice of the index that reaches into it: one binary search for each stretch, whose ranges
    and ids must fit a task; raise ``cells`` with the number of ids."""
    i = index.where("end_idx >= start_idx")
    top = i.agg(F.max("end_idx")).first()[0]
    step = max(1, -(-((top or 0) + 1) // cells))
    cell = lambda c: F.floor(F.col(c) / step).cast("long")
    slices = i.select("bundle_id", "start_idx", "end_idx", "byte_offset", "byte_len", F.explode(F.sequence(cell("start_idx"), cell("end_idx"))).alias("cell"))
    asked = requests.where("sample_id IS NOT NULL").select(cell("sample_id").alias("cell"), "sample_id")

    def search(ids: pd.DataFrame, held: pd.DataFrame) -> pd.DataFrame:
        held = held.sort_values("start_idx")
        x, s, e = ids["sample_id"].to_numpy(), held["start_idx"].to_numpy(), held["end_idx"].to_numpy()
        k = np.searchsorted(s, x, side="right") - 1
        ok = (k >= 0) & (x <= e[k]) if len(s) else np.zeros(len(x), bool)
        x, k = x[ok], k[ok]
        hit = held.iloc[k]
        return pd.DataFrame({"sample_id": x, "bundle_id": hit["bundle_id"].to_numpy(), "text_pos": x - s[k], "byte_offset": hit["byte_offset"].to_numpy(), "byte_len": hit["byte_len"].to_numpy()})

    return asked.groupBy("cell").cogroup(slices.groupBy("cell")).applyInPandas(search, "sample_id long, bundle_id long, text_pos long, byte_offset long, byte_len long")


def prune_one(index: DataFrame, sample_id: int) -> DataFrame:
    """A single id: predicates on start and end that reach the scan, where row groups are skipped by their statistics."""
    hit = index.where((F.col("start_idx") <= sample_id) & (F.col("end_idx") >= sample_id)).limit(1)
    return hit.select(F.lit(sample_id).cast("long").alias("sample_id"), "bundle_id", (F.lit(sample_id) - F.col("start_idx")).alias("text_pos"), "byte_offset", "byte_len")


STRATEGIES = {"search": range_search, "theta": range_theta, "binned": range_binned, "asof": range_asof, "cogroup": range_cogroup}


def locate(requests: DataFrame, index: DataFrame, header: dict, force: str | None = None, how: str = "inner", strict: bool = False) -> DataFrame:
    """Picks the rule from the header (kind, ratio); ``force`` names one: direct, ratio, hash, search, theta, binned, asof,
    cogroup."""
    rule = force or {FIXED: "ratio", HYBRID: "binned"}.get(header["kind"], "direct")
    if rule == "direct":
        out = direct(requests, index)
    elif rule == "ratio":
        out = ratio(requests, index, header["ratio"])
    elif rule == "hash":
        out = hashed(requests, index)
    else:
        out = STRATEGIES[rule](requests, index)
    if how == "left" or strict:
        out = requests.select("sample_id").join(out, "sample_id", "left")
    if strict:
        out = out.withColumn("bundle_id", F.when(F.col("bundle_id").isNull(), F.raise_error(F.concat(F.lit("no sample "), F.coalesce(F.col("sample_id").cast("string"), F.lit("null"))))).otherwise(F.col("bundle_id")))
    return out
