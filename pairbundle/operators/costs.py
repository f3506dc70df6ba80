"""Cost measures of the layouts, from counts and bytes. Times come from a profile whose values are ours; counts and bytes need none."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairbundle.model import FIXED, HYBRID
from pairbundle.operators.layouts import per_layout


@dataclass(frozen=True)
class Profile:
    """What storage costs: milliseconds to open, seek and create, MB a second from storage, from memory and in sequential writes."""

    open_ms: float = 0.5
    seek_ms: float = 0.1
    read_mb_s: float = 500.0
    cached_mb_s: float = 8000.0
    create_ms: float = 5.0
    write_mb_s: float = 200.0


META_BYTES = 4096


def index_width(kind: str = "kind", entry: int = 4) -> Column:
    """Bytes of index for each bundle: an offset, or for hybrid corpora a start, an end, an offset and the offset array's entry."""
    return F.when(F.col(kind) == HYBRID, F.lit(4 * entry)).otherwise(F.lit(entry))


def index_bytes(stats: DataFrame, entry: int = 4, path_bytes: int = 0) -> DataFrame:
    n, m = F.col("n_pairs"), F.col("n_bundles")
    return per_layout(stats, {
        "loose": {"index_bytes": F.lit(0).cast("long")},
        "path_table": {"index_bytes": F.col("text_bytes") + n * entry + m * path_bytes},
        "pair_record": {"index_bytes": n * entry},
        "bundle": {"index_bytes": (m * index_width(entry=entry)).cast("long")},
        "bundle_hash": {"index_bytes": n * (2 * entry) + m * entry},
    })


def file_counts(stats: DataFrame, modalities: int = 2) -> DataFrame:
    n, m = F.col("n_pairs"), F.col("n_bundles")
    one = F.lit(1).cast("long")
    return per_layout(stats, {"loose": {"files": n * modalities}, "path_table": {"files": m + 1}, "pair_record": {"files": one}, "bundle": {"files": one}})


def storage(stats: DataFrame, meta_bytes: int = META_BYTES, media_scale: int = 1, entry: int = 4, modalities: int = 2) -> DataFrame:
    """files and storage_bytes, with so many bytes of metadata for each file; media may be scaled to the sizes of real media."""
    n, m, t = F.col("n_pairs"), F.col("n_bundles"), F.col("text_bytes")
    once, each = F.col("media_bytes") * media_scale, F.col("dup_bytes") * media_scale
    sizes = {"loose": (n * modalities, each + t), "path_table": (m + 1, once + t), "pair_record": (F.lit(1).cast("long"), each + t + n * entry), "bundle": (F.lit(1).cast("long"), (once + t + m * index_width(entry=entry)).cast("long"))}
    return per_layout(stats, {k: {"files": f.cast("long"), "storage_bytes": (b + f * meta_bytes).cast("long")} for k, (f, b) in sizes.items()})


def duplication(stats: DataFrame) -> DataFrame:
    return stats.withColumn("duplication", F.col("dup_bytes") / F.col("media_bytes"))


def read_amplification(stats: DataFrame) -> DataFrame:
    """Bytes of the bundle over bytes of the pair, averaged over accesses."""
    return stats.withColumn("amplification", F.col("touched_bytes") / (F.col("dup_bytes") + F.col("text_bytes")))


def _touched(media_scale: int) -> dict[str, Column]:
    """Bytes that an access touches, on average."""
    n, d, t = F.col("n_pairs"), F.col("dup_bytes") * media_scale, F.col("text_bytes")
    grown = F.col("touched_bytes") + F.col("dup_bytes") * (media_scale - 1)
    return {"loose": (d + t) / n, "path_table": d / n, "pair_record": (d + t) / n, "bundle": grown / n}


OPENS = {"loose": 2, "path_table": 1, "pair_record": 0, "bundle": 0}


def load_rate(stats: DataFrame, profile: Profile = Profile(), media_scale: int = 1, shares=tuple(range(10, 101, 10)), compare_ns: float = 0.0, fetch: str = "object") -> DataFrame:  # noqa: B008
    """Samples a second of a random epoch for each layout and cache share. Hits follow the closed form where accesses share objects;
    ``fetch='pair'`` reads the pair alone from a bundle and leaves nothing for its siblings."""
    shared = {"path_table", "bundle"} if fetch == "object" else {"path_table"}
    reuse = 1 - F.col("n_bundles") / F.col("n_pairs")
    touched = _touched(media_scale)
    if fetch == "pair":
        touched["bundle"] = touched["pair_record"]
    rows = stats.withColumn("share", F.explode(F.array(*[F.lit(s) for s in shares])))

    def rate(layout: str) -> Column:
        hit = F.col("share") / 100 * reuse if layout in shared else F.lit(0.0)
        mb = touched[layout] / 1e6
        ms = OPENS[layout] * profile.open_ms + (1 - hit) * (profile.seek_ms + mb / profile.read_mb_s * 1000) + hit * (mb / profile.cached_mb_s * 1000)
        if layout == "bundle" and compare_ns:
            ms = ms + F.log2(F.col("n_bundles") + 1) * compare_ns / 1e6
        return 1000 / ms

    return per_layout(rows, {k: {"rate": rate(k)} for k in OPENS})


def rate_of_hits(stats: DataFrame, hits: DataFrame, profile: Profile = Profile(), media_scale: int = 1) -> DataFrame:  # noqa: B008
    """As ``load_rate``, with the share of hits from a simulated cache (corpus, layout, share, hit_share) instead of the closed form."""
    shares = hits.select("share").distinct()
    touched = per_layout(stats.select("corpus", "n_pairs", "dup_bytes", "text_bytes", "touched_bytes"), {k: {"mb": c / 1e6, "opens": F.lit(OPENS[k])} for k, c in _touched(media_scale).items()})
    rows = touched.select("corpus", "layout", "mb", "opens").join(F.broadcast(shares)).join(F.broadcast(hits), ["corpus", "layout", "share"], "left").fillna({"hit_share": 0.0})
    hit, mb = F.col("hit_share"), F.col("mb")
    ms = F.col("opens") * profile.open_ms + (1 - hit) * (profile.seek_ms + mb / profile.read_mb_s * 1000) + hit * (mb / profile.cached_mb_s * 1000)
    return rows.select("corpus", "layout", "share", "hit_share", (1000 / ms).alias("rate"))


def write_rate(stats: DataFrame, profile: Profile = Profile(), media_scale: int = 1) -> DataFrame:  # noqa: B008
    """Samples a second of a bulk copy: a cost for each file and for each byte."""
    s = storage(stats, meta_bytes=0, media_scale=media_scale)
    seconds = F.col("files") * profile.create_ms / 1000 + F.col("storage_bytes") / 1e6 / profile.write_mb_s
    return s.withColumn("rate", F.col("n_pairs") / seconds)


def epoch_time(configs: DataFrame, overlap: bool = True) -> DataFrame:
    """compute_s, io_s -> epoch_s: input that compute hides costs nothing."""
    wait = F.greatest(F.lit(0.0), F.col("io_s") - F.col("compute_s")) if overlap else F.col("io_s")
    return configs.withColumn("epoch_s", F.col("compute_s") + wait)


def kind_rule() -> Column:
    return F.when(F.col("kind") == FIXED, "ratio").when(F.col("kind") == HYBRID, "range_tree").otherwise("direct")
