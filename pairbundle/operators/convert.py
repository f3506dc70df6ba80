"""The converter: pairs -> fingerprints -> clusters -> bundles with ids, ranges and offsets -> header."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairbundle.model import FIXED, HYBRID, ONE_TO_ONE, UNI_MODAL
from pairbundle.operators import addressing

HASHES = {"md5": F.md5, "sha256": lambda c: F.sha2(c, 256), "xxhash64": lambda c: F.lower(F.hex(F.xxhash64(c)))}


def fingerprint(pairs: DataFrame, algo: str = "md5", verify: bool = False, hash_function=None) -> DataFrame:
    """Adds fingerprint and media_bytes; rows without media are rejected. ``verify`` tells contents of equal hash and length apart by
    comparing each with the representative, and numbers those that differ."""
    rows = pairs.where("media IS NOT NULL")
    made = (hash_function or HASHES[algo])(F.col("media"))
    rows = rows.withColumn("fingerprint", made).withColumn("media_bytes", F.octet_length("media").cast("long"))
    if not verify:
        return rows
    contents = rows.select("fingerprint", "media_bytes", "media").distinct()
    apart = contents.groupBy("fingerprint", "media_bytes").agg(F.count("*").alias("n")).where("n > 1")
    from pyspark.sql import Window

    split = contents.join(apart, ["fingerprint", "media_bytes"], "left_semi").withColumn("collision_no", F.row_number().over(Window.partitionBy("fingerprint", "media_bytes").orderBy("media")) - 1)
    out = rows.join(split, ["fingerprint", "media_bytes", "media"], "left").fillna({"collision_no": 0})
    return out.withColumn("fingerprint", F.when(F.col("collision_no") > 0, F.concat_ws("#", "fingerprint", "collision_no")).otherwise(F.col("fingerprint")))


def clusters(marked: DataFrame, text_policy: str = "all") -> DataFrame:
    """fingerprint, media_bytes, rep_ord, n_texts, text_bytes, n_copies: counts alone. The media never enter the shuffle."""
    light = marked.select("fingerprint", "media_bytes", "pair_ord", "text")
    if text_policy == "distinct":
        light = light.groupBy("fingerprint", "media_bytes", "text").agg(F.min("pair_ord").alias("pair_ord"))
    return light.groupBy("fingerprint", "media_bytes").agg(F.min("pair_ord").alias("rep_ord"), F.count("text").alias("n_texts"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).cast("long").alias("text_bytes"), F.count("*").alias("n_copies"))


def detect(marked: DataFrame, text_policy: str = "all", text_order: str = "source") -> DataFrame:
    """Clusters with their texts, in source order or by text."""
    light = marked.select("fingerprint", "media_bytes", "pair_ord", "text", "src_id")
    if text_policy == "distinct":
        light = light.groupBy("fingerprint", "media_bytes", "text").agg(F.min("pair_ord").alias("pair_ord"), F.min_by("src_id", "pair_ord").alias("src_id"))
    entry = F.struct("pair_ord", "text", "src_id") if text_order == "source" else F.struct("text", "pair_ord", "src_id")
    texts = F.array_sort(F.collect_list(F.when(F.col("text").isNotNull(), entry)))
    out = light.groupBy("fingerprint", "media_bytes").agg(F.min("pair_ord").alias("rep_ord"), texts.alias("texts"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).cast("long").alias("text_bytes"), F.count("*").alias("n_copies"))
    shaped = F.transform("texts", lambda t: F.struct(t["pair_ord"].alias("pair_ord"), t["text"].alias("text"), t["src_id"].alias("src_id")))
    return out.withColumn("texts", shaped).withColumn("n_texts", F.size("texts").cast("long"))


def assemble(pairs: DataFrame, found: DataFrame, mode: str = "representative") -> DataFrame:
    """Adds the media: fetched once for each cluster by its representative, after all else is known. ``mode='single_pass'`` takes marked
    pairs instead and carries the media through one aggregation, for small media."""
    if mode == "single_pass":
        return found.join(pairs.groupBy("fingerprint", "media_bytes").agg(F.min_by("media", "pair_ord").alias("media")), ["fingerprint", "media_bytes"])
    return found.join(pairs.select(F.col("pair_ord").alias("rep_ord"), "media"), "rep_ord")


def bundles(pairs: DataFrame, order: str = "first_seen", algo: str = "md5", text_policy: str = "all", text_order: str = "source", mode: str = "distributed") -> DataFrame:
    """Whole bundles, numbered: media, texts, ranges and offsets."""
    marked = fingerprint(pairs, algo)
    index = addressing.number(clusters(marked, text_policy), order, mode)
    texts = detect(marked, text_policy, text_order).select("fingerprint", "media_bytes", "texts")
    return assemble(pairs, index.join(texts, ["fingerprint", "media_bytes"]))


def summary(pairs: DataFrame, order: str = "first_seen", mode: str = "distributed") -> DataFrame:
    """What the converter records about each bundle, without media or texts."""
    out = addressing.number(clusters(fingerprint(pairs)), order, mode)
    return out.select("bundle_id", "fingerprint", "media_bytes", "n_texts", "text_bytes", "start_idx", "end_idx", "byte_offset", "byte_len")


def kind_of(least: Column, most: Column) -> Column:
    return F.when(most == 0, UNI_MODAL).when((least == 1) & (most == 1), ONE_TO_ONE).when((least == most), FIXED).otherwise(HYBRID)


def classify(found: DataFrame) -> DataFrame:
    """kind, n_pairs, n_bundles, ratio (of fixed corpora) and body_bytes: one row from one aggregation over clusters or bundles."""
    body = F.coalesce(F.sum(addressing.encoded_length()), F.lit(0)).alias("body_bytes")
    one = found.agg(F.min("n_texts").alias("least"), F.max("n_texts").alias("most"), F.coalesce(F.sum("n_texts"), F.lit(0)).alias("n_texts"), F.count("*").alias("n_bundles"), body)
    kind = F.when(F.col("n_bundles") == 0, UNI_MODAL).otherwise(kind_of(F.col("least"), F.col("most")))
    return one.select(kind.alias("kind"), F.when(kind == UNI_MODAL, F.col("n_bundles")).otherwise(F.col("n_texts")).alias("n_pairs"), "n_bundles", F.when(kind == FIXED, F.col("least")).alias("ratio"), "body_bytes")


def build_header(index: DataFrame) -> DataFrame:
    """The header's one row. The offsets, and the ranges of hybrid corpora, stay a table: the index itself."""
    return classify(index).withColumn("indexed_by", F.when(F.col("kind") == FIXED, "ratio").when(F.col("kind") == HYBRID, "range_tree").otherwise("direct"))


def redundancy_report(marked: DataFrame) -> DataFrame:
    """Clusters by their copies: how often, and the media bytes that storing once saves."""
    return clusters(marked).groupBy("n_copies").agg(F.count("*").alias("n_clusters"), F.sum((F.col("n_copies") - 1) * F.col("media_bytes")).alias("saved_bytes"))


def as_pairs(found: DataFrame) -> DataFrame:
    """Bundles -> pairs: sample_id, pair_ord, media, text, src_id. A bundle without texts gives its media with a null text."""
    each = found.select("start_idx", "rep_ord", "media", F.posexplode_outer("texts").alias("pos", "t"))
    return each.select((F.col("start_idx") + F.coalesce("pos", F.lit(0))).alias("sample_id"), F.coalesce("t.pair_ord", "rep_ord").alias("pair_ord"), "media", "t.text", "t.src_id")


def verify_roundtrip(pairs: DataFrame, found: DataFrame) -> DataFrame:
    """Pairs that differ after conversion and back, in either direction: none."""
    light = lambda df: df.select("pair_ord", F.md5("media").alias("media"), "text")
    a, b = light(pairs), light(as_pairs(found))
    return a.exceptAll(b).withColumn("side", F.lit("lost")).union(b.exceptAll(a).withColumn("side", F.lit("added")))


def merge(stored: DataFrame, more: DataFrame) -> DataFrame:
    """Bundles of two generations (fingerprint, media_bytes, rep_ord, media, texts) as one: texts of equal media are joined in order."""
    both = stored.select("fingerprint", "media_bytes", "rep_ord", "media", "texts").unionByName(more.select("fingerprint", "media_bytes", "rep_ord", "media", "texts"))
    texts = F.array_sort(F.flatten(F.collect_list("texts")))
    out = both.groupBy("fingerprint", "media_bytes").agg(F.min("rep_ord").alias("rep_ord"), F.min_by("media", "rep_ord").alias("media"), texts.alias("texts"))
    sizes = F.aggregate("texts", F.lit(0).cast("long"), lambda s, t: s + F.octet_length(t["text"]))
    return out.withColumn("n_texts", F.size("texts").cast("long")).withColumn("text_bytes", sizes)
