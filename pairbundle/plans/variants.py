"""Variants, controls and simulated measures beside the main workloads, each on given tables; with a SQL oracle where SQL can say it."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairbundle.functions import udfs
from pairbundle.operators import cachesim, compare, convert, costs, layouts, locate, rangetree, reader, sampler
from pairbundle.operators.relational import ORACLES as RELATIONAL
from pairbundle.plans import sql
from pairbundle.plans.workloads import ORACLES, SCALE, SUMMARY, TRAINING, found, index, query, rounded, stand_ins, stand_ins_sql, stats
from pairbundle.sources import legacy
from pairbundle.sources.container import index_table, load_pairs, read_container, write_container
from pairbundle.sources.corpora import corpus, table
from pairbundle.sources.shared import shared_path, staged
from pairbundle.streaming import ingest, windows

def _joined(texts: str = "texts"):
    return F.md5(F.array_join(F.transform(texts, lambda t: t["text"]), "\n"))


def _texts_sql(name: str) -> str:
    return f"SELECT md5(media) AS fingerprint, count(text)::BIGINT AS n, md5(string_agg(text, chr(10) ORDER BY pair_ord)) AS texts_md5 FROM ({sql.PAIRS[name]}) GROUP BY 1"


# Conversion


@query("SELECT md5(media) AS media_md5, 1::BIGINT AS n_contents, count(*)::BIGINT AS n_copies FROM (" + sql.PAIRS["doc_copies"] + ") GROUP BY 1")
def fingerprint_verified(spark, sf_dir):
    """A hash of two digits, so that most contents collide: verification tells them apart."""
    short = lambda c: F.substring(F.md5(c), 1, 2)
    marked = convert.fingerprint(corpus(spark, sf_dir, "doc_copies"), verify=True, hash_function=short)
    out = marked.groupBy("fingerprint", "media_bytes").agg(F.min(F.md5("media")).alias("media_md5"), F.count_distinct("media").alias("n_contents"), F.count("*").alias("n_copies"))
    return out.select("media_md5", "n_contents", "n_copies")


def _from_layout(layout: str):
    oracle = f"SELECT bundle_id, start_idx, end_idx, i.fingerprint, n AS n_texts, texts_md5 FROM ({sql.index('conv_turns')}) i JOIN ({_texts_sql('conv_turns')}) t ON i.fingerprint = t.fingerprint"

    @query(oracle, f"convert_from_{layout}")
    def run(spark, sf_dir):
        """One command: a layout on storage becomes a container, which is then scanned."""
        whole = staged(convert.bundles(corpus(spark, sf_dir, "conv_turns")), "whole")
        src, dest = shared_path(spark, layout), shared_path(spark, "box")
        if layout == "path_table":
            legacy.write_path_table(whole, src)
        else:
            {"loose": legacy.write_loose, "pair_record": legacy.write_pair_record}[layout](convert.as_pairs(whole), src)
        legacy.run_conversion(spark, src, layout, dest)
        joined = F.md5(F.array_join("texts", "\n"))
        return read_container(spark, dest).select("bundle_id", "start_idx", "end_idx", F.md5("media").alias("fingerprint"), F.size("texts").cast("long").alias("n_texts"), joined.alias("texts_md5"))


for _layout in ("loose", "path_table", "pair_record"):
    _from_layout(_layout)


@query(f"SELECT layout, objects::BIGINT AS objects, bytes::BIGINT AS bytes FROM (SELECT unnest(['loose', 'path_table', 'pair_record']) AS layout, unnest([2 * n_pairs, n_bundles, n_pairs]) AS objects, unnest([dup_bytes + text_bytes, media_bytes, dup_bytes + text_bytes + 8 * n_pairs]) AS bytes FROM ({sql.stats(('page_links',))}))")
def layouts_reverse(spark, sf_dir):
    """Bundles back to each baseline: objects and bytes of what would be written."""
    whole, out = staged(convert.bundles(corpus(spark, sf_dir, "page_links")), "whole"), None
    held = {"loose": (layouts.explode_to(whole, "loose"), "content"), "path_table": (layouts.explode_to(whole, "path_table")[1], "content"), "pair_record": (layouts.explode_to(whole, "pair_record"), "record")}
    for layout, (rows, column) in held.items():
        one = rows.agg(F.lit(layout).alias("layout"), F.count("*").alias("objects"), F.sum(F.octet_length(column)).alias("bytes")).select("layout", "objects", "bytes")
        out = one if out is None else out.union(one)
    return out


_COUNTED = ("doc_copies", "page_links", "docs_uni")


@query(" UNION ALL ".join(f"SELECT '{n}' AS corpus, count(*)::BIGINT AS pairs, count(*)::BIGINT AS same FROM ({sql.PAIRS[n]})" for n in _COUNTED))
def roundtrip_counts(spark, sf_dir):
    """Pairs before and after conversion and back that are the same row, counted."""
    out = None
    for name in _COUNTED:
        pairs = corpus(spark, sf_dir, name)
        light = lambda df: df.select("pair_ord", F.md5("media").alias("m"), "text")
        back = light(convert.as_pairs(convert.bundles(pairs))).withColumn("b", F.lit(1))
        a = light(pairs)
        same = (a["pair_ord"] == back["pair_ord"]) & (a["m"] == back["m"]) & a["text"].eqNullSafe(back["text"])
        one = a.join(back, same, "left").agg(F.lit(name).alias("corpus"), F.count("*").alias("pairs"), F.count("b").alias("same")).select("corpus", "pairs", "same")
        out = one if out is None else out.union(one)
    return out


@query(_texts_sql("conv_turns").replace("count(text)::BIGINT AS n,", "count(text)::BIGINT AS n_texts,"))
def merge_texts(spark, sf_dir):
    """Three generations merged: the texts of each bundle, in order."""
    pairs = corpus(spark, sf_dir, "conv_turns")
    part = lambda k: convert.bundles(pairs.where(F.col("pair_ord") % 3 == k))
    both = convert.merge(part(0), part(1))
    return convert.merge(both, part(2)).select("fingerprint", "n_texts", _joined().alias("texts_md5"))


@query(f"SELECT bundle_id, n AS n_texts, texts_md5 FROM ({sql.index('page_links')}) i JOIN ({_texts_sql('page_links')}) t ON i.fingerprint = t.fingerprint")
def parquet_layout_texts(spark, sf_dir):
    """The Parquet layout, read for its texts: no media column is scanned."""
    path = shared_path(spark, "bundles")
    layouts.write_bundles(convert.bundles(corpus(spark, sf_dir, "page_links")), path)
    return spark.read.parquet(path).select("bundle_id", F.size("texts").cast("long").alias("n_texts"), _joined().alias("texts_md5"))


@query(f"SELECT bundle_id, start_idx, end_idx, byte_len FROM ({sql.index('orders_lineitems')})")
def container_index(spark, sf_dir):
    """The index of a written container, from the ends of its shards alone."""
    path = shared_path(spark, "box")
    write_container(convert.bundles(corpus(spark, sf_dir, "orders_lineitems")), path)
    return index_table(spark, path).select("bundle_id", "start_idx", "end_idx", "byte_len")


@query(f"SELECT bundle_id, start_idx, end_idx, fingerprint, n_texts FROM ({sql.index('page_links')}) WHERE bundle_id BETWEEN 10 AND 29 AND start_idx > 40")
def container_pruned(spark, sf_dir):
    """A scan with filters on the index's columns; they reach the source where the session allows it."""
    path = shared_path(spark, "box")
    write_container(convert.bundles(corpus(spark, sf_dir, "page_links")), path, 8)
    rows = read_container(spark, path).where("bundle_id >= 10 AND bundle_id <= 29 AND start_idx > 40")
    return rows.select("bundle_id", "start_idx", "end_idx", F.md5("media").alias("fingerprint"), F.size("texts").cast("long").alias("n_texts"))


@query(f"SELECT bundle_id, byte_len, i.fingerprint, n AS n_texts, texts_md5 FROM ({sql.index('conv_turns')}) i JOIN ({_texts_sql('conv_turns')}) t ON i.fingerprint = t.fingerprint")
def encode_decode(spark, sf_dir):
    """Bundles through the binary encoding and back, in Arrow batches."""
    import pyarrow as pa

    whole = convert.bundles(corpus(spark, sf_dir, "conv_turns"))
    data = whole.select("bundle_id", udfs.encoder()(F.col("media").cast("binary"), F.transform("texts", lambda t: t["text"])).alias("data"))

    def decode(batches):
        from pairbundle.sources.container import decode_bundle

        for b in batches:
            held = [decode_bundle(d.as_py()) for d in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([h[2] for h in held], pa.int64()), pa.array([h[0] for h in held], pa.binary()), pa.array([h[1] for h in held], pa.list_(pa.string()))], names=["bundle_id", "byte_len", "media", "texts"])

    back = data.mapInArrow(decode, "bundle_id long, byte_len long, media binary, texts array<string>")
    return back.select("bundle_id", "byte_len", F.md5("media").alias("fingerprint"), F.size("texts").cast("long").alias("n_texts"), F.md5(F.array_join("texts", "\n")).alias("texts_md5"))


_LOADED = ("page_links", "conv_turns", "doc_cap5", "doc_copies")


def _loaded_sql(name: str) -> str:
    texts = f"SELECT md5(media) AS fingerprint, text, row_number() OVER (PARTITION BY md5(media) ORDER BY pair_ord) - 1 AS pos FROM ({sql.PAIRS[name]})"
    return f"SELECT s.sample_id, s.bundle_id, t.fingerprint AS media_md5, t.text FROM ({sql.samples(name)}) s JOIN ({sql.index(name)}) i ON s.bundle_id = i.bundle_id JOIN ({texts}) t ON t.fingerprint = i.fingerprint AND t.pos = s.text_pos"


def _load(name: str):
    @query(_loaded_sql(name), f"container_load_{name}")
    def run(spark, sf_dir):
        """Every id of an epoch, loaded from a written container."""
        path = shared_path(spark, "box")
        write_container(convert.bundles(corpus(spark, sf_dir, name)), path)
        ids = index_table(spark, path).select(F.explode(F.sequence("start_idx", F.greatest("start_idx", "end_idx"))).alias("sample_id"))
        return load_pairs(ids, path).select("sample_id", "bundle_id", F.md5("media").alias("media_md5"), "text")


for _name in _LOADED:
    _load(_name)


# Lookup


@query(f"SELECT sample_id, sample_id AS record_id FROM ({sql.samples('page_links')})")
def locate_pair_array(spark, sf_dir):
    idx = index(spark, sf_dir, "page_links")
    ids = sampler.sample_ids(idx).select("sample_id")
    return locate.pair_array(ids.union(spark.createDataFrame([(-1,), (1 << 40,)], "sample_id long")), convert.classify(idx).first()["n_pairs"])


_MISSING = ("page_links", "doc_cap5", "docs_uni")


@query(" UNION ALL ".join(f"SELECT '{n}' AS corpus, a.sample_id, s.bundle_id, s.text_pos FROM (SELECT sample_id FROM ({sql.samples(n)}) UNION ALL SELECT unnest([-2, 1000000000000, NULL])::BIGINT) a LEFT JOIN ({sql.samples(n)}) s ON a.sample_id = s.sample_id" for n in _MISSING))
def locate_missing(spark, sf_dir):
    """Ids outside all ranges, and null ones, keep their row, with nulls."""
    out = None
    for name in _MISSING:
        idx = index(spark, sf_dir, name)
        more = spark.createDataFrame([(-2,), (10**12,), (None,)], "sample_id long")
        asked = sampler.sample_ids(idx).select("sample_id").union(more)
        one = locate.locate(asked, idx, convert.classify(idx).first().asDict(), how="left").select(F.lit(name).alias("corpus"), "sample_id", "bundle_id", "text_pos")
        out = one if out is None else out.union(one)
    return out


@query(f"SELECT sample_id, bundle_id, text_pos, byte_offset, byte_len FROM ({sql.samples('orders_lineitems')})")
def locate_range_cogroup(spark, sf_dir):
    idx = index(spark, sf_dir, "orders_lineitems")
    return locate.locate(sampler.sample_ids(idx).select("sample_id"), idx, convert.classify(idx).first().asDict(), "cogroup").select(*locate.COLUMNS)


@query(f"SELECT s.sample_id, s.bundle_id, t.fingerprint AS media_md5, t.text FROM ({sql.samples('page_links')}) s JOIN ({sql.index('page_links')}) i ON s.bundle_id = i.bundle_id JOIN (SELECT md5(media) AS fingerprint, text, row_number() OVER (PARTITION BY md5(media) ORDER BY pair_ord) - 1 AS pos FROM ({sql.PAIRS['page_links']})) t ON t.fingerprint = i.fingerprint AND t.pos = s.text_pos WHERE s.sample_id = 100")
def get_pair(spark, sf_dir):
    whole = staged(convert.bundles(corpus(spark, sf_dir, "page_links")), "whole")
    return reader.get(whole, 100).select("sample_id", "bundle_id", F.md5("media").alias("media_md5"), "text")


@query(f"SELECT bundle_id // 512 AS part, count(*)::BIGINT AS nodes, sum(n_texts)::BIGINT AS found, true AS balanced FROM ({sql.index('orders_lineitems')}) WHERE n_texts > 0 GROUP BY 1")
def tree_insertions(spark, sf_dir):
    """Trees grown by insertion, one for each 512 bundles: nodes, ids found at their place, and whether order and balance hold."""
    def grow(part: pd.DataFrame) -> pd.DataFrame:
        root, hits = None, 0
        rows = part.sort_values("byte_len")[["start_idx", "end_idx", "byte_offset"]].to_numpy().tolist()  # no order of ids
        for start, end, at in rows:
            root = rangetree.insert(root, start, end, at)
        for start, end, at in rows:
            hits += sum(rangetree.find(root, k) == (at, k - start) for k in range(start, end + 1))
        nodes = rangetree.check(root)
        return pd.DataFrame({"part": [int(part["part"].iloc[0])], "nodes": [nodes], "found": [hits], "balanced": [root.height <= 1.4405 * (nodes + 2).bit_length() + 1]})

    idx = index(spark, sf_dir, "orders_lineitems").where("end_idx >= start_idx").withColumn("part", F.expr("bundle_id DIV 512"))
    return idx.groupBy("part").applyInPandas(grow, "part long, nodes long, found long, balanced boolean")


ORACLES["stream_randomness"] = f"""WITH rows AS (SELECT sample_id, (sample_id // 500)::BIGINT AS shard FROM ({sql.samples('doc_cap5')})),
runs AS (SELECT sample_id, md5('42|0|shard|' || shard) AS s, (row_number() OVER (PARTITION BY shard ORDER BY sample_id) - 1) // 64 AS run, md5('42|0|' || sample_id) AS k FROM rows),
placed AS (SELECT sample_id, row_number() OVER (ORDER BY s, run, k, sample_id) - 1 AS step FROM runs)
SELECT count(*)::BIGINT AS n, avg(abs(step - sample_id)) AS displacement, avg(abs(step - sample_id)) / (count(*) / 3) AS share FROM placed"""


# Cache reuse: by simulation, for both layouts that share objects


def _objects(layout: str, scale: int) -> str:
    """Bytes of the object that an access asks for: the whole bundle, or the media file of a path table."""
    return f"byte_len + {scale - 1} * media_bytes" if layout == "bundle" else f"{scale} * media_bytes"


def _accesses(spark, sf_dir, name: str, layout: str, scale: int, epochs: int = 1, page: int = 0) -> tuple[DataFrame, int]:
    idx = index(spark, sf_dir, name, "fingerprint")
    sizes = idx.select("bundle_id", F.expr(_objects(layout, scale)).cast("long").alias("object_bytes"))
    sizes = cachesim.paged(sizes, page) if page else sizes
    rows = cachesim.stream(staged(sampler.epoch_all(idx), "epoch", narrow=True), sizes)
    return cachesim.repeated(rows, epochs) if epochs > 1 else rows, sizes.agg(F.sum("object_bytes")).first()[0]


def _sweep(spark, sf_dir, name: str, layout: str, scale: int = 1, **options) -> DataFrame:
    rows, body = _accesses(spark, sf_dir, name, layout, scale, **options)
    return cachesim.sweep(cachesim.distances(rows), body).select(F.col("share").cast("long").alias("share"), "accesses", "hits", "miss_bytes")


def _sweep_sql(name: str, layout: str, scale: int = 1, epochs: int = 1, page: int = 0) -> str:
    size = _objects(layout, scale)
    size = f"(ceil(({size}) / {page}.0) * {page})" if page else f"({size})"
    order = "fingerprint, media_bytes"
    steps = f"(SELECT e.step + k.k * (SELECT count(*) FROM ({sql.samples(name, order)})) AS step, e.bundle_id FROM ({sql.epoch(name, order)}) e, range(0, {epochs}) k(k))"
    return f"""SELECT share, count(*)::BIGINT AS accesses, sum(CASE WHEN hit THEN 1 ELSE 0 END)::BIGINT AS hits, sum(CASE WHEN hit THEN 0 ELSE size END)::BIGINT AS miss_bytes FROM (
WITH sized AS (SELECT bundle_id, {size}::BIGINT AS size FROM ({sql.index(name, order)})),
acc AS (SELECT s.step, s.bundle_id, z.size, lag(s.step) OVER (PARTITION BY s.bundle_id ORDER BY s.step) AS prev FROM {steps} s JOIN sized z ON s.bundle_id = z.bundle_id),
far AS (SELECT a.step, a.size, CASE WHEN a.prev IS NOT NULL THEN coalesce((SELECT sum(b.size) FROM acc b WHERE b.step > a.prev AND b.step < a.step AND coalesce(b.prev, -1) <= a.prev), 0) END AS distance FROM acc a)
SELECT share, size, coalesce(distance + size <= body * share // 100, false) AS hit FROM far, (SELECT sum(size) AS body FROM sized), range(10, 101, 10) r(share)) GROUP BY share"""


@query(_sweep_sql("page_links", "path_table"))
def cache_sweep_path_table(spark, sf_dir):
    """Media files of a path table share a cache as bundles do, without the texts."""
    return _sweep(spark, sf_dir, "page_links", "path_table")


@query(_sweep_sql("page_links", "bundle", page=4096))
def cache_pages(spark, sf_dir):
    """The granularity of a page cache."""
    return _sweep(spark, sf_dir, "page_links", "bundle", page=4096)


@query(_sweep_sql("page_links", "bundle", epochs=2))
def cache_warm_epochs(spark, sf_dir):
    """Two epochs, the cache kept between them."""
    return _sweep(spark, sf_dir, "page_links", "bundle", epochs=2)


@query(f"SELECT share, n_pairs AS accesses, 0::BIGINT AS hits, body_bytes AS miss_bytes FROM ({sql.stats(('pages_url',))}), range(10, 101, 10) s(share)")
def cache_no_sharing(spark, sf_dir):
    """The control: one text for each media object leaves nothing to reuse within an epoch."""
    return _sweep(spark, sf_dir, "pages_url", "bundle")


_SIMULATED = ("page_links", "conv_turns")


def _simulated(spark, sf_dir, names=_SIMULATED) -> DataFrame:
    """corpus, layout, share, hit_share, rate: the loading model with hits from the simulated cache."""
    s, hits = stats(spark, sf_dir, names), None
    for name in names:
        for layout in ("path_table", "bundle"):
            one = _sweep(spark, sf_dir, name, layout, SCALE).select(F.lit(name).alias("corpus"), F.lit(layout).alias("layout"), "share", (F.col("hits") / F.col("accesses")).alias("hit_share"))
            hits = one if hits is None else hits.union(one)
    return costs.rate_of_hits(s, hits, media_scale=SCALE)


def _simulated_sql() -> str:
    hits = " UNION ALL ".join(f"SELECT '{n}' AS corpus, '{layout}' AS layout, share, hits / accesses AS hit FROM ({_sweep_sql(n, layout, SCALE)})" for n in _SIMULATED for layout in ("path_table", "bundle"))
    mb = f"CASE layout WHEN 'path_table' THEN dup_bytes * {SCALE} WHEN 'bundle' THEN touched_bytes + dup_bytes * {SCALE - 1} ELSE dup_bytes * {SCALE} + text_bytes END / n_pairs / 1e6"
    rows = f"SELECT s.corpus, l.layout, sh.share, coalesce(h.hit, 0) AS hit_share, l.opens, {mb.replace('layout', 'l.layout')} AS mb FROM ({sql.stats(_SIMULATED)}) s, (VALUES ('loose', 2), ('path_table', 1), ('pair_record', 0), ('bundle', 0)) l(layout, opens), range(10, 101, 10) sh(share) LEFT JOIN ({hits}) h ON h.corpus = s.corpus AND h.layout = l.layout AND h.share = sh.share"
    return f"SELECT corpus, layout, share, hit_share, 1000 / (opens * 0.5 + (1 - hit_share) * (0.1 + mb / 500 * 1000) + hit_share * (mb / 8000 * 1000)) AS rate FROM ({rows})"


@query(f"SELECT corpus, layout, share, round(hit_share, 6) AS hit_share, round(rate, 4) AS rate FROM ({_simulated_sql()})")
def load_simulated(spark, sf_dir):
    return rounded(rounded(_simulated(spark, sf_dir), "hit_share"), "rate", digits=4)


@query(f"SELECT corpus, min(CASE WHEN a >= b THEN share END) AS share FROM (SELECT corpus, share, max(CASE WHEN layout = 'path_table' THEN rate END) AS a, max(CASE WHEN layout = 'pair_record' THEN rate END) AS b FROM ({_simulated_sql()}) GROUP BY corpus, share) GROUP BY corpus")
def cache_crossover_simulated(spark, sf_dir):
    """The least share at which a path table overtakes pair records, by simulated hits."""
    return compare.crossover(_simulated(spark, sf_dir))


@query(f"SELECT corpus, round(avg(ours / best), 6) AS mean_speedup, round(avg(1 - best / ours), 6) AS mean_loss FROM (SELECT corpus, share, max(CASE WHEN layout = 'bundle' THEN rate END) AS ours, max(CASE WHEN layout <> 'bundle' THEN rate END) AS best FROM ({_simulated_sql()}) GROUP BY corpus, share) GROUP BY corpus")
def averaging_per_setting(spark, sf_dir):
    """The third average: speed-up and loss of each cache share, then their means."""
    each = compare.vs_best(_simulated(spark, sf_dir), keys=("corpus", "share"))
    loss = 1 - F.col("best_baseline") / F.col("ours")
    return each.groupBy("corpus").agg(F.round(F.avg("speedup"), 6).alias("mean_speedup"), F.round(F.avg(loss), 6).alias("mean_loss"))


# Measures


@query(f"SELECT round(avg(p / a), 6) AS mean_ratio, round(avg(1 - a / p), 6) AS mean_reduction FROM (SELECT 4.0::DOUBLE * n AS p, (m * (CASE WHEN kind = 'hybrid' THEN 16 ELSE 4 END))::DOUBLE AS a FROM ({stand_ins_sql()}))")
def published_mean_ratio(spark, sf_dir):
    """Mean of the ratios of index sizes, and mean of the reductions: two averages over the corpora that stand for the seven published data sets."""
    rows = stand_ins(spark, sf_dir).select((F.col("n_pairs") * 4.0).alias("p"), (F.col("n_bundles") * costs.index_width()).cast("double").alias("a"))
    return rounded(compare.mean_ratio(rows, "p", "a"), "mean_ratio", "mean_reduction")


_COMPARE_NS, _PROBE_NS = 50, 120
_RATED = ("doc_cap5", "page_links", "orders_lineitems", "pages_url")


@query(f"""SELECT h.corpus, round(1 - a.ns / {_PROBE_NS}.0, 6) AS lookup_gain, round(1000 / (ms + {_PROBE_NS} / 1e6), 4) AS hash_rate, round(1000 / (ms + a.ns / 1e6), 4) AS adaptive_rate
FROM (SELECT corpus, 1000 / rate AS ms FROM ({sql.load_rate(_RATED, SCALE)}) WHERE layout = 'bundle' AND share = 50) h
JOIN (SELECT corpus, CASE WHEN kind = 'hybrid' THEN log2(n_bundles + 1) * {_COMPARE_NS} ELSE 0 END AS ns FROM ({sql.stats(_RATED)})) a ON h.corpus = a.corpus""")
def index_tradeoff_rates(spark, sf_dir):
    """Loading rates with a hash and with the adaptive index, at half of the cache: nanoseconds of a probe and of a comparison are ours."""
    s = stats(spark, sf_dir, _RATED)
    ms = costs.load_rate(s, media_scale=SCALE, shares=(50,)).where("layout = 'bundle'").select("corpus", (1000 / F.col("rate")).alias("ms"))
    ns = s.select("corpus", F.when(F.col("kind") == "hybrid", F.log2(F.col("n_bundles") + 1) * _COMPARE_NS).otherwise(F.lit(0.0)).alias("ns"))
    rate = lambda extra: F.round(1000 / (F.col("ms") + extra / 1e6), 4)
    return ms.join(ns, "corpus").select("corpus", F.round(1 - F.col("ns") / _PROBE_NS, 6).alias("lookup_gain"), rate(F.lit(_PROBE_NS)).alias("hash_rate"), rate(F.col("ns")).alias("adaptive_rate"))


@query("SELECT model, layout, round((compute_s + greatest(0, io_s - compute_s))::DOUBLE, 4) AS epoch_s FROM (SELECT model, layout, (20 + 0.02 * parameters + 0.05 * trained) * again / 1000.0 * n_pairs / 100 AS compute_s, n_pairs / rate AS io_s FROM (VALUES " + ", ".join(f"('{n}', {p}, {t}, {a})" for n, p, t, a in TRAINING) + f") m(model, parameters, trained, again), ({sql.load_rate(('doc_cap5',), SCALE)}) r WHERE share = 50)")
def epoch_time_simulated(spark, sf_dir):
    """Epoch times with the input time of each layout on a corpus, hidden behind compute where that is longer. Compute seconds are ours."""
    entries = [F.struct(F.lit(n).alias("model"), F.lit(float(p)).alias("parameters"), F.lit(float(t)).alias("trained"), F.lit(a).alias("again")) for n, p, t, a in TRAINING]
    m = spark.range(1).select(F.inline(F.array(*entries)))
    r = costs.load_rate(stats(spark, sf_dir, ("doc_cap5",)), media_scale=SCALE, shares=(50,)).select("layout", "n_pairs", (F.col("n_pairs") / F.col("rate")).alias("io_s"))
    compute = (20 + 0.02 * F.col("parameters") + 0.05 * F.col("trained")) * F.col("again") / 1000.0 * F.col("n_pairs") / 100
    rows = r.join(F.broadcast(m)).select("model", "layout", compute.alias("compute_s"), "io_s")
    return costs.epoch_time(rows).select("model", "layout", F.round("epoch_s", 4).alias("epoch_s"))


# Further operators


@query("SELECT doc_id, lang FROM (SELECT doc_id, lang, ('0x' || substr(md5('7|' || doc_id), 1, 8))::BIGINT AS h FROM documents) WHERE h < 4294967296 * CASE lang WHEN 'en' THEN 0.2 WHEN 'de' THEN 0.5 WHEN 'fr' THEN 0.5 WHEN 'es' THEN 1.0 ELSE 0 END", "op_sample_stratified_hash")
def sample_stratified_hash(spark, sf_dir):
    """A sample by language that any engine draws alike."""
    h = F.conv(F.substring(F.md5(F.concat(F.lit("7|"), F.col("doc_id").cast("string"))), 1, 8), 16, 10).cast("long")
    share = F.when(F.col("lang") == "en", 0.2).when(F.col("lang").isin("de", "fr"), 0.5).when(F.col("lang") == "es", 1.0).otherwise(0.0)
    return table(spark, sf_dir, "documents").where(h < 4294967296 * share).select("doc_id", "lang")


@query("SELECT p_brand, mad(p_size)::DOUBLE AS mad_size FROM part GROUP BY p_brand", "op_agg_pandas")
def agg_pandas(spark, sf_dir):
    """A grouped aggregate that Spark lacks, in pandas: the median absolute deviation. A group must fit one task."""
    @F.pandas_udf("double")
    def mad(v: pd.Series) -> float:
        return float((v - v.median()).abs().median())

    return table(spark, sf_dir, "part").groupBy("p_brand").agg(mad("p_size").alias("mad_size"))


@query("SELECT o_orderpriority, min(o_orderstatus) AS least, max(o_clerk_free) AS most FROM (SELECT *, concat_ws('|', o_orderstatus, o_orderkey) AS o_clerk_free FROM orders) GROUP BY 1", "op_agg_sorted")
def agg_sorted(spark, sf_dir):
    """Aggregates of strings, whose buffers can't change in place: the plan sorts."""
    return table(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.min("o_orderstatus").alias("least"), F.max(F.concat_ws("|", "o_orderstatus", "o_orderkey")).alias("most"))


@query("SELECT d.doc_id, b.item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)", "op_join_contains")
def join_contains(spark, sf_dir):
    hits = corpus(spark, sf_dir, "bench_hits")
    return hits.select(F.expr("pair_ord DIV 1000").alias("doc_id"), F.pmod("pair_ord", F.lit(1000)).alias("item_id"))


# Streams: run to the end of their input, and read again as tables


def _table_stream(spark, rows: DataFrame, files: int) -> DataFrame:
    path = shared_path(spark, "arrivals")
    rows.repartition(files).write.parquet(path)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)


def _drained(stream: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over all that has arrived; the table it leaves."""
    spark = stream.sparkSession
    path, state = shared_path(spark, "left"), shared_path(spark, "state")
    writer = stream.writeStream.option("checkpointLocation", state).trigger(availableNow=True).outputMode(mode)
    if mode == "append":
        writer = writer.format("parquet").option("path", path)
    else:  # each batch restates the whole result
        writer = writer.foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(path))
    writer.start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


@query(f"SELECT {SUMMARY} FROM ({sql.index('doc_copies')})")
def stream_conversion(spark, sf_dir):
    """Pairs that arrive in four files become generations of bundles, compacted into one numbering."""
    pairs, path, out = corpus(spark, sf_dir, "doc_copies"), shared_path(spark, "arrivals"), shared_path(spark, "generations")
    pairs.repartition(4).write.parquet(path)
    ingest.ingest(ingest.pair_stream(spark, path), out, shared_path(spark, "state")).awaitTermination()
    return ingest.compact(spark, out).select("bundle_id", "fingerprint", "media_bytes", F.size("texts").cast("long").alias("n_texts"), "text_bytes", "start_idx", "end_idx", "byte_offset", "byte_len")


@query("SELECT DISTINCT md5(text) AS fingerprint FROM documents")
def stream_first_copies(spark, sf_dir):
    """One row of each content, over all micro-batches."""
    stream = _table_stream(spark, corpus(spark, sf_dir, "doc_copies"), 4)
    return _drained(ingest.first_copies(stream).select("fingerprint"), "append")


def _window_stream(shape: str, twin: str):
    @query(RELATIONAL[twin], f"stream_{shape}")
    def run(spark, sf_dir):
        return _drained(getattr(windows, shape)(_table_stream(spark, table(spark, sf_dir, "events"), 3)), "complete")


for _shape, _twin in (("tumbling", "op_ts_tumbling"), ("sliding", "op_ts_sliding"), ("sessions", "op_ts_session")):
    _window_stream(_shape, _twin)


@query(RELATIONAL["op_join_interval"])
def stream_interval_join(spark, sf_dir):
    """Both sides arrive at once, so that no row is late."""
    stream = _table_stream(spark, table(spark, sf_dir, "events"), 1)
    return _drained(windows.interval_join(stream, stream), "append")


@query("SELECT event_id, e.user_id, p.seen FROM events e JOIN (SELECT user_id, count(*)::BIGINT AS seen FROM events GROUP BY user_id) p ON e.user_id = p.user_id")
def stream_with_profile(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    profile = e.groupBy("user_id").agg(F.count("*").alias("seen"))
    return _drained(windows.with_profile(_table_stream(spark, e, 3), profile).select("event_id", "user_id", "seen"), "append")
