"""The experiment workloads on the given tables, each with its SQL oracle."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairbundle.operators import addressing, cachesim, compare, convert, costs, layouts, locate, rangetree, reader, sampler
from pairbundle.plans import sql
from pairbundle.sources import legacy
from pairbundle.sources.container import read_container, read_header, size_ratio, validate, write_container
from pairbundle.sources.corpora import CORPORA, SEVEN, corpus
from pairbundle.sources.shared import shared_path, staged

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

MANY = tuple(n for n in CORPORA if n != "vec_uni")


def query(oracle: str | None = None, name: str | None = None):
    """Registers a workload and its oracle."""

    def add(f):
        QUERIES[name or f.__name__] = f
        if oracle:
            ORACLES[name or f.__name__] = oracle
        return f

    return add


def found(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return convert.clusters(convert.fingerprint(corpus(spark, sf_dir, name)))


def stats(spark: SparkSession, sf_dir: str, names=SEVEN) -> DataFrame:
    """One row for each corpus, written once: workloads read it several times."""
    return staged(layouts.stats({n: found(spark, sf_dir, n) for n in names}), "stats", narrow=True)


def index(spark: SparkSession, sf_dir: str, name: str, order: str = "first_seen") -> DataFrame:
    return staged(addressing.number(found(spark, sf_dir, name), order), "index", narrow=True)


def rounded(df: DataFrame, *names: str, digits: int = 6) -> DataFrame:
    return df.withColumns({n: F.round(F.col(n), digits) for n in names})


# Statistics and classification


@query(f"SELECT corpus, kind, n_bundles, n_pairs, round(n_pairs / n_bundles, 6) AS ratio, round(media_bytes / n_bundles, 6) AS mean_media, round(text_bytes / n_pairs, 6) AS mean_text, body_bytes, round(dup_bytes / media_bytes, 6) AS duplication FROM ({sql.stats(MANY)})")
def profile_all(spark, sf_dir):
    s = costs.duplication(stats(spark, sf_dir, MANY))
    out = s.select("corpus", "kind", "n_bundles", "n_pairs", (F.col("n_pairs") / F.col("n_bundles")).alias("ratio"), (F.col("media_bytes") / F.col("n_bundles")).alias("mean_media"), (F.col("text_bytes") / F.col("n_pairs")).alias("mean_text"), "body_bytes", "duplication")
    return rounded(out, "ratio", "mean_media", "mean_text", "duplication")


@query(f"SELECT corpus, kind, n_pairs, n_bundles FROM ({sql.stats(tuple(CORPORA))})")
def classify_all(spark, sf_dir):
    return stats(spark, sf_dir, tuple(CORPORA)).select("corpus", "kind", "n_pairs", "n_bundles")


@query(f"SELECT round(media_bytes / n_bundles, 6) AS mean_media, round(text_bytes / n_pairs, 6) AS mean_text, round((media_bytes / n_bundles) / (text_bytes / n_pairs), 6) AS size_ratio, (media_bytes / n_bundles) / (text_bytes / n_pairs) > 10 AS media_dominant FROM ({sql.stats(('user_events',))})")
def size_ratio_check(spark, sf_dir):
    return rounded(size_ratio(found(spark, sf_dir, "user_events")), "mean_media", "mean_text")


@query(f"SELECT n_copies, count(*)::BIGINT AS n_clusters, sum((n_copies - 1) * media_bytes)::BIGINT AS saved_bytes FROM ({sql.clusters('doc_copies')}) GROUP BY n_copies")
def redundancy_report(spark, sf_dir):
    return convert.redundancy_report(convert.fingerprint(corpus(spark, sf_dir, "doc_copies")))


# Conversion

SUMMARY = "bundle_id, fingerprint, media_bytes, n_texts, text_bytes, start_idx, end_idx, byte_offset, byte_len"


def _conversion(name: str):
    QUERIES[f"convert_{name}"] = lambda spark, sf_dir: convert.summary(corpus(spark, sf_dir, name))
    ORACLES[f"convert_{name}"] = f"SELECT {SUMMARY} FROM ({sql.index(name)})"


for _n in ("region_nations", "doc_copies", "doc_cap5", "doc_cap20", "doc_caphyb", "page_links", "orders_lineitems", "customer_orders", "part_lineitems", "supplier_lineitems", "user_events", "conv_turns", "doc_labels", "bench_hits", "pages_url", "vec_label", "docs_uni"):
    _conversion(_n)


@query(f"SELECT {SUMMARY} FROM ({sql.index('doc_copies', 'fingerprint, media_bytes')})")
def convert_by_fingerprint(spark, sf_dir):
    return convert.summary(corpus(spark, sf_dir, "doc_copies"), "fingerprint")


@query(f"SELECT {SUMMARY} FROM ({sql.index('doc_copies')})")
def convert_window_mode(spark, sf_dir):
    return convert.summary(corpus(spark, sf_dir, "doc_copies"), mode="window")


@query(f"SELECT bundle_id, shard_id, byte_offset - min(byte_offset) OVER (PARTITION BY shard_id) AS local_offset FROM (SELECT bundle_id, byte_offset, (byte_offset // 100000)::BIGINT AS shard_id FROM ({sql.index('page_links')}))")
def container_shards(spark, sf_dir):
    return addressing.shard(index(spark, sf_dir, "page_links"), 100_000).select("bundle_id", "shard_id", "local_offset")


@query(f"SELECT kind, n_pairs, n_bundles, CASE WHEN kind = 'fixed' THEN n_pairs // n_bundles END::BIGINT AS ratio, body_bytes, CASE kind WHEN 'fixed' THEN 'ratio' WHEN 'hybrid' THEN 'range_tree' ELSE 'direct' END AS indexed_by FROM ({sql.stats(('doc_cap5', 'page_links', 'pages_url', 'docs_uni'))})")
def build_headers(spark, sf_dir):
    out = None
    for n in ("doc_cap5", "page_links", "pages_url", "docs_uni"):
        one = convert.build_header(found(spark, sf_dir, n))
        out = one if out is None else out.union(one)
    return out


@query("SELECT fingerprint, rep_ord, n_texts, texts_md5 FROM (SELECT md5(media) AS fingerprint, min(pair_ord)::BIGINT AS rep_ord, count(DISTINCT text)::BIGINT AS n_texts, md5(string_agg(DISTINCT text, chr(10) ORDER BY text)) AS texts_md5 FROM (" + sql.PAIRS["page_links"] + ") GROUP BY md5(media), strlen(media))")
def detect_distinct_texts(spark, sf_dir):
    d = convert.detect(convert.fingerprint(corpus(spark, sf_dir, "page_links")), "distinct", "text")
    return d.select("fingerprint", "rep_ord", "n_texts", F.md5(F.array_join(F.transform("texts", lambda t: t["text"]), "\n")).alias("texts_md5"))


@query("SELECT md5(media) AS fingerprint, count(*)::BIGINT AS n_texts, strlen(any_value(media))::BIGINT AS media_bytes, md5(string_agg(text, chr(10) ORDER BY pair_ord)) AS texts_md5 FROM (" + sql.PAIRS["conv_turns"] + ") GROUP BY 1")
def assemble_single_pass(spark, sf_dir):
    marked = convert.fingerprint(corpus(spark, sf_dir, "conv_turns"))
    b = convert.assemble(marked, convert.detect(marked), "single_pass")
    return b.select("fingerprint", "n_texts", F.octet_length("media").cast("long").alias("media_bytes"), F.md5(F.array_join(F.transform("texts", lambda t: t["text"]), "\n")).alias("texts_md5"))


def _roundtrip(name: str):
    def run(spark, sf_dir):
        pairs = corpus(spark, sf_dir, name)
        return convert.verify_roundtrip(pairs, convert.bundles(pairs)).groupBy("side").agg(F.count("*").alias("pairs"))

    QUERIES[f"roundtrip_{name}"] = run
    ORACLES[f"roundtrip_{name}"] = "SELECT 'lost' AS side, 0::BIGINT AS pairs WHERE false"


for _n in ("doc_cap5", "page_links", "doc_copies", "orders_lineitems", "conv_turns", "docs_uni"):
    _roundtrip(_n)


@query("SELECT layout, (SELECT count(*) FROM embeddings)::BIGINT AS pairs, 0::BIGINT AS differing FROM (VALUES ('loose'), ('path_table'), ('pair_record')) t(layout)")
def roundtrip_binary(spark, sf_dir):
    """Media of arbitrary bytes, no text in any encoding, written in each layout, read back and converted: pairs compared, and how many differ."""
    raw = F.unhex(F.concat(F.lit("FFD8FF00"), F.md5("media")))
    found = staged(convert.bundles(corpus(spark, sf_dir, "vec_label").withColumn("media", raw)), "binary")
    pairs = staged(convert.as_pairs(found), "binary-pairs")
    light = lambda df, ord_: df.select(F.col(ord_).cast("long").alias("k"), F.md5("media").alias("m"), "text")
    want, out = light(pairs, "sample_id"), None
    writers = {"loose": lambda p: legacy.write_loose(pairs, p), "path_table": lambda p: legacy.write_path_table(found, p), "pair_record": lambda p: legacy.write_pair_record(pairs, p)}
    for layout, write in writers.items():
        path = shared_path(spark, layout)
        write(path)
        back = light(convert.as_pairs(convert.bundles(legacy.read_pairs(spark, path, layout))), "sample_id")
        met = want.withColumn("a", F.lit(1)).join(back.withColumn("b", F.lit(1)), ["k", "m", "text"], "full")
        same = F.col("a").isNotNull() & F.col("b").isNotNull()
        one = met.agg(F.count("a").alias("pairs"), F.sum((~same).cast("long")).alias("differing")).select(F.lit(layout).alias("layout"), "pairs", "differing")
        out = one if out is None else out.union(one)
    return out


@query("SELECT kind, n_pairs, n_bundles FROM (" + sql.stats(("docs_uni", "page_links", "pages_url", "doc_cap5")) + ")")
def container_header_kinds(spark, sf_dir):
    """What a written container records of its pairing, for each kind."""
    rows = []
    for name in ("docs_uni", "page_links", "pages_url", "doc_cap5"):
        path = shared_path(spark, f"box-{name}")
        write_container(convert.bundles(corpus(spark, sf_dir, name)), path)
        head = read_header(path)
        rows.append((head["kind"], head["n_pairs"], head["n_bundles"]))
    return spark.createDataFrame(rows, "kind string, n_pairs long, n_bundles long")


@query(f"SELECT bundle_id, start_idx, end_idx, media_bytes, n_texts, text_bytes FROM ({sql.index('page_links')})")
def scan_container(spark, sf_dir):
    """A container written and scanned: what each of its bundles holds."""
    path = shared_path(spark, "box")
    write_container(convert.bundles(corpus(spark, sf_dir, "page_links")), path)
    size = F.aggregate("texts", F.lit(0).cast("long"), lambda s, t: s + F.octet_length(t))
    return read_container(spark, path).select("bundle_id", "start_idx", "end_idx", F.octet_length("media").cast("long").alias("media_bytes"), F.size("texts").cast("long").alias("n_texts"), size.alias("text_bytes"))


@query("SELECT 0::BIGINT AS bundle_id, 0::BIGINT AS start_idx, 0::BIGINT AS end_idx, 0::BIGINT AS byte_offset, 0::BIGINT AS byte_len WHERE false")
def container_valid(spark, sf_dir):
    return validate(index(spark, sf_dir, "orders_lineitems"))


@query(f"SELECT fingerprint, n_texts, text_bytes FROM ({sql.clusters('doc_copies')})")
def merge_generations(spark, sf_dir):
    """Two batches of pairs, converted apart and merged, against one conversion."""
    pairs = corpus(spark, sf_dir, "doc_copies")
    part = lambda k: convert.bundles(pairs.where(F.col("pair_ord") % 2 == k))
    return convert.merge(part(0), part(1)).select("fingerprint", "n_texts", "text_bytes")


# Layouts, storage, index


@query(f"SELECT corpus, layout, files, storage_bytes FROM ({sql.storage(SEVEN)})")
def storage_by_layout(spark, sf_dir):
    return costs.storage(stats(spark, sf_dir)).select("corpus", "layout", "files", "storage_bytes")


def _normalized(to: str, scale: int = 1):
    return f"SELECT corpus, layout, storage_bytes, round(storage_bytes / max(CASE WHEN layout = '{to}' THEN storage_bytes END) OVER (PARTITION BY corpus), 6) AS normalized FROM ({sql.storage(SEVEN, scale)})"


@query(_normalized("path_table"))
def storage_normalized(spark, sf_dir):
    return rounded(compare.normalize(costs.storage(stats(spark, sf_dir)), "storage_bytes", "path_table"), "normalized").select("corpus", "layout", "storage_bytes", "normalized")


@query(_normalized("bundle", 56))
def storage_real_media(spark, sf_dir):
    """Over ours, with media scaled to the size of real images."""
    return rounded(compare.normalize(costs.storage(stats(spark, sf_dir), media_scale=56), "storage_bytes", "bundle"), "normalized").select("corpus", "layout", "storage_bytes", "normalized")


@query(f"SELECT corpus, layout, files FROM ({sql.storage(SEVEN)})")
def file_counts(spark, sf_dir):
    return costs.file_counts(stats(spark, sf_dir)).select("corpus", "layout", "files")


@query(f"SELECT corpus, layout, index_bytes FROM ({sql.index_bytes(SEVEN)})")
def index_bytes_by_layout(spark, sf_dir):
    return costs.index_bytes(stats(spark, sf_dir)).select("corpus", "layout", "index_bytes")


@query(f"SELECT i.corpus, index_bytes, storage_bytes, round(index_bytes / storage_bytes, 9) AS share, round(index_bytes / storage_bytes * 1000, 6) AS memory_share_at_1000 FROM ({sql.index_bytes(SEVEN)}) i JOIN ({sql.storage(SEVEN)}) s ON i.corpus = s.corpus AND s.layout = 'bundle' WHERE i.layout = 'bundle'")
def index_share(spark, sf_dir):
    s = stats(spark, sf_dir)
    i = costs.index_bytes(s).where("layout = 'bundle'").select("corpus", "index_bytes")
    t = costs.storage(s).where("layout = 'bundle'").select("corpus", "storage_bytes")
    share = F.col("index_bytes") / F.col("storage_bytes")
    return i.join(t, "corpus").select("corpus", "index_bytes", "storage_bytes", F.round(share, 9).alias("share"), F.round(share * 1000, 6).alias("memory_share_at_1000"))


@query(f"SELECT corpus, max(CASE WHEN layout = 'bundle_hash' THEN index_bytes END)::BIGINT AS hash_bytes, max(CASE WHEN layout = 'bundle' THEN index_bytes END)::BIGINT AS adaptive_bytes, round(1 - max(CASE WHEN layout = 'bundle' THEN index_bytes END) / max(CASE WHEN layout = 'bundle_hash' THEN index_bytes END), 6) AS saved FROM ({sql.index_bytes(SEVEN)}) GROUP BY corpus")
def index_tradeoff(spark, sf_dir):
    pick = lambda layout: F.max(F.when(F.col("layout") == layout, F.col("index_bytes")))
    out = costs.index_bytes(stats(spark, sf_dir)).groupBy("corpus").agg(pick("bundle_hash").alias("hash_bytes"), pick("bundle").alias("adaptive_bytes"))
    return out.withColumn("saved", F.round(1 - F.col("adaptive_bytes") / F.col("hash_bytes"), 6))


#: Media and pair counts solved from the published index sizes, and the kind of each data set.
PUBLISHED = (("Flickr30k", 31012, 155071, "fixed"), ("F30-E", 31782, 158916, "fixed"), ("MSCOCO", 117957, 589868, "fixed"), ("VQA2", 88751, 443757, "hybrid"), ("GQA", 69338, 943000, "hybrid"), ("MSRVTT", 10000, 200000, "fixed"), ("Clotho", 3937, 19690, "fixed"))

#: The corpus that stands for each published data set.
STAND_INS = {"Flickr30k": "doc_cap5", "F30-E": "doc_cap5", "MSCOCO": "doc_cap5", "VQA2": "page_links", "GQA": "doc_caphyb", "MSRVTT": "doc_cap20", "Clotho": "doc_cap5"}
STANDING = tuple(dict.fromkeys(STAND_INS.values()))


def stand_ins_sql() -> str:
    values = ", ".join(f"('{n}', '{STAND_INS[n]}', {m}, {p}, '{k}')" for n, m, p, k in PUBLISHED)
    return f"SELECT name, t.corpus, s.n_bundles AS m, s.n_pairs AS n, s.kind, published_m, published_n, published_kind FROM (VALUES {values}) t(name, corpus, published_m, published_n, published_kind) JOIN ({sql.stats(STANDING)}) s ON s.corpus = t.corpus"


def published(spark: SparkSession) -> DataFrame:
    entries = [F.struct(F.lit(n).alias("name"), F.lit(STAND_INS[n]).alias("corpus"), F.lit(m).cast("long").alias("n_bundles"), F.lit(p).cast("long").alias("n_pairs"), F.lit(k).alias("kind"), F.lit(0).cast("long").alias("text_bytes")) for n, m, p, k in PUBLISHED]
    return spark.range(1).select(F.inline(F.array(*entries)))


def stand_ins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The published data sets by name, each with the counts and kind of its corpus on the given tables."""
    names = F.broadcast(published(spark).select("name", "corpus"))
    return stats(spark, sf_dir, STANDING).select("corpus", "n_bundles", "n_pairs", "kind", "text_bytes").join(names, "corpus")


def index_comparison(rows: DataFrame) -> DataFrame:
    """Index sizes in KB, the share that the adaptive index saves, and the size of the pair record's over it."""
    pick = lambda layout: F.max(F.when(F.col("layout") == layout, F.col("index_bytes")))
    out = costs.index_bytes(rows).groupBy("name", "corpus").agg(pick("bundle_hash").alias("h"), pick("bundle").alias("a"), pick("pair_record").alias("p"))
    return out.select("name", "corpus", F.round(F.col("h") / 1024, 2).alias("hash_kb"), F.round(F.col("a") / 1024, 2).alias("adaptive_kb"), F.round(1 - F.col("a") / F.col("h"), 4).alias("saved"), F.round(F.col("p") / F.col("a"), 3).alias("pair_record_ratio"))


_WIDTH = "(CASE WHEN {}kind = 'hybrid' THEN 16 ELSE 4 END)"


@query(f"""SELECT name, corpus, round((8 * n + 4 * m) / 1024.0, 2) AS hash_kb, round(m * {_WIDTH.format('')} / 1024.0, 2) AS adaptive_kb, round(1 - m * {_WIDTH.format('')} / (8.0 * n + 4 * m), 4) AS saved, round(4.0 * n / (m * {_WIDTH.format('')}), 3) AS pair_record_ratio,
round(1 - published_m * {_WIDTH.format('published_')} / (8.0 * published_n + 4 * published_m), 4) AS published_saved, round(4.0 * published_n / (published_m * {_WIDTH.format('published_')}), 3) AS published_ratio FROM ({stand_ins_sql()})""")
def published_index_check(spark, sf_dir):
    """Index sizes of the corpora that stand for the published data sets, beside what the published counts give by the same formulas."""
    want = index_comparison(published(spark)).select("name", F.col("saved").alias("published_saved"), F.col("pair_record_ratio").alias("published_ratio"))
    return index_comparison(stand_ins(spark, sf_dir)).join(F.broadcast(want), "name")


@query(f"""SELECT s.corpus, s.layout, CASE WHEN s.layout IN ('loose', 'pair_record') THEN s.dup_bytes ELSE s.media_bytes END > 1.5 * s.media_bytes AS redundancy, s.files > 2 AS small_files, s.layout IN ('loose', 'pair_record') AS cache_unfriendly, i.index_bytes > 4.0 * b.index_bytes AS heavy_index
FROM ({sql.storage(SEVEN)}) s JOIN ({sql.index_bytes(SEVEN)}) i ON s.corpus = i.corpus AND s.layout = i.layout JOIN ({sql.index_bytes(SEVEN)}) b ON s.corpus = b.corpus AND b.layout = 'bundle'""")
def issues_matrix(spark, sf_dir):
    s = stats(spark, sf_dir)
    i = costs.index_bytes(s).select("corpus", "layout", "index_bytes")
    b = i.where("layout = 'bundle'").select("corpus", F.col("index_bytes").alias("bundle_index_bytes"))
    apart = F.col("layout").isin("loose", "pair_record")
    rows = costs.file_counts(s).withColumn("media_written", F.when(apart, F.col("dup_bytes")).otherwise(F.col("media_bytes"))).withColumn("shares", ~apart)
    return compare.issue_matrix(rows.select("corpus", "layout", "media_written", "media_bytes", "files", "shares").join(i, ["corpus", "layout"]).join(b, "corpus"))


@query(f"SELECT corpus, round(touched_bytes / (dup_bytes + text_bytes), 6) AS amplification FROM ({sql.stats(SEVEN)})")
def read_amplification(spark, sf_dir):
    return rounded(costs.read_amplification(stats(spark, sf_dir)), "amplification").select("corpus", "amplification")


# Lookup


def _requests(idx: DataFrame) -> DataFrame:
    """Every id."""
    return sampler.sample_ids(idx).select("sample_id")


def _lookup(key: str, name: str, force: str | None):
    def run(spark, sf_dir):
        idx = index(spark, sf_dir, name)
        head = convert.classify(idx).first().asDict()
        return locate.locate(_requests(idx), idx, head, force).select(*locate.COLUMNS)

    QUERIES[key] = run
    ORACLES[key] = f"SELECT sample_id, bundle_id, text_pos, byte_offset, byte_len FROM ({sql.samples(name)})"


for _key, _name, _force in (("locate_direct", "pages_url", None), ("locate_ratio", "doc_cap5", None), ("locate_range", "orders_lineitems", None), ("locate_range_search", "orders_lineitems", "search"), ("locate_range_asof", "orders_lineitems", "asof"), ("locate_range_theta", "page_links", "theta"), ("locate_hash", "orders_lineitems", "hash"), ("locate_uni_modal", "docs_uni", None), ("locate_adaptive_links", "page_links", None)):
    _lookup(_key, _name, _force)


@query(f"SELECT sample_id, bundle_id, text_pos, byte_offset, byte_len FROM ({sql.samples('page_links')}) WHERE sample_id = 777")
def locate_one(spark, sf_dir):
    return locate.prune_one(index(spark, sf_dir, "page_links"), 777).select(*locate.COLUMNS)


@query(f"SELECT (start_idx + p) AS sample_id, bundle_id, fingerprint FROM ({sql.index('page_links')}), range(0, 30) r(p) WHERE p <= end_idx - start_idx AND (start_idx + p) % 50 = 0")
def get_many_pairs(spark, sf_dir):
    b = convert.bundles(corpus(spark, sf_dir, "page_links"))
    head = convert.classify(b).first().asDict()
    wanted = spark.range(0, head["n_pairs"], 50).withColumnRenamed("id", "sample_id")
    return reader.get_many(wanted, b, head).select("sample_id", "bundle_id", F.md5("media").alias("fingerprint"))


@query(f"WITH RECURSIVE n AS (SELECT count(*)::BIGINT AS m FROM ({sql.index('orders_lineitems')})), seg(lo, hi, depth) AS (SELECT 0::BIGINT, m, 1 FROM n UNION ALL SELECT unnest([lo, (lo + hi) // 2 + 1]), unnest([(lo + hi) // 2, hi]), depth + 1 FROM seg WHERE lo < hi) SELECT depth, count(*)::BIGINT AS nodes FROM seg WHERE lo < hi GROUP BY depth")
def tree_depths(spark, sf_dir):
    return rangetree.depth_stats(rangetree.build(index(spark, sf_dir, "orders_lineitems")))


@query(f"SELECT sample_id, bundle_id FROM ({sql.samples('page_links')})")
def tree_walk(spark, sf_dir):
    idx = index(spark, sf_dir, "page_links")
    tree = staged(rangetree.build(idx), "tree", narrow=True)
    return rangetree.lookup_trace(tree, _requests(idx)).select("sample_id", "bundle_id")


@query(f"WITH RECURSIVE r AS (SELECT row_number() OVER (ORDER BY start_idx) - 1 AS node, n_texts FROM ({sql.index('page_links')})), n AS (SELECT count(*)::BIGINT AS m FROM r), seg(lo, hi, depth) AS (SELECT 0::BIGINT, m, 1 FROM n UNION ALL SELECT unnest([lo, (lo + hi) // 2 + 1]), unnest([(lo + hi) // 2, hi]), depth + 1 FROM seg WHERE lo < hi) SELECT round(sum(depth * n_texts) / sum(n_texts), 6) AS mean_comparisons, max(depth)::INTEGER AS max_comparisons, sum(n_texts)::BIGINT AS lookups FROM seg JOIN r ON r.node = (lo + hi) // 2 WHERE lo < hi")
def tree_comparisons(spark, sf_dir):
    """Comparisons of a lookup by the balanced tree, over every id: mean and most."""
    idx = index(spark, sf_dir, "page_links")
    tree = staged(rangetree.build(idx), "tree", narrow=True)
    trace = rangetree.lookup_trace(tree, _requests(idx))
    return trace.agg(F.round(F.avg("comparisons"), 6).alias("mean_comparisons"), F.max("comparisons").alias("max_comparisons"), F.count("*").alias("lookups"))


# Epochs


@query(f"SELECT step, sample_id, bundle_id, text_pos FROM ({sql.epoch('page_links')})")
def epoch_all(spark, sf_dir):
    return sampler.epoch_all(index(spark, sf_dir, "page_links"))


@query(f"SELECT step, sample_id FROM ({sql.epoch('doc_cap5')})")
def epoch_order(spark, sf_dir):
    return sampler.permute(sampler.sample_ids(index(spark, sf_dir, "doc_cap5")))


@query(f"SELECT bundle_id, text_pos, start_idx + text_pos AS sample_id FROM (SELECT bundle_id, start_idx, ('0x' || substr(md5('42|0|' || bundle_id), 1, 8))::BIGINT % (end_idx - start_idx + 1) AS text_pos FROM ({sql.index('page_links')}))")
def epoch_one(spark, sf_dir):
    return sampler.epoch_one(index(spark, sf_dir, "page_links"))


@query(f"SELECT bundle_id, md5(t) AS sequence_md5 FROM ({sql.index('doc_cap5')}) i JOIN (SELECT md5(media) AS fingerprint, string_agg(text, ' ' ORDER BY pair_ord) AS t FROM ({sql.PAIRS['doc_cap5']}) GROUP BY 1) x ON i.fingerprint = x.fingerprint")
def epoch_concat(spark, sf_dir):
    return sampler.epoch_concat(convert.bundles(corpus(spark, sf_dir, "doc_cap5"))).select("bundle_id", F.md5("sequence").alias("sequence_md5"))


@query(f"SELECT step, sample_id, step // 64 AS batch_no, (step // 64) % 3 AS worker FROM ({sql.epoch('page_links')}) WHERE step // 64 < (SELECT count(*) FROM ({sql.samples('page_links')})) // 64")
def epoch_batches(spark, sf_dir):
    out = sampler.batches(sampler.epoch_all(index(spark, sf_dir, "page_links")), 64, 3, drop_last=True)
    return out.select("step", "sample_id", "batch_no", F.col("worker").cast("long").alias("worker"))


@query()
def stream_randomness(spark, sf_dir):
    """Mean displacement in a shard stream against a third of the length, which a full permutation has."""
    idx = index(spark, sf_dir, "doc_cap5")
    return sampler.randomness(sampler.stream_shuffle(sampler.sample_ids(idx), F.floor(F.col("sample_id") / 500)))


# Cache reuse


def _accesses(spark, sf_dir, name):
    idx = index(spark, sf_dir, name, "fingerprint")
    epoch = staged(sampler.epoch_all(idx), "epoch", narrow=True)
    return cachesim.stream(epoch, idx.select("bundle_id", F.col("byte_len").alias("object_bytes"))), idx


_D, _ACC = sql.distances("page_links")


@query(f"WITH {_ACC} SELECT step, bundle_id AS object_id, byte_len AS object_bytes, distance::BIGINT AS distance FROM ({_D})")
def recency_distances(spark, sf_dir):
    return cachesim.distances(_accesses(spark, sf_dir, "page_links")[0]).select("step", "object_id", "object_bytes", "distance")


_DR, _ACCR = sql.distances("region_nations")


@query(f"WITH {_ACCR} SELECT step, bundle_id AS object_id, byte_len AS object_bytes, distance::BIGINT AS distance FROM ({_DR})")
def recency_by_definition(spark, sf_dir):
    return cachesim.distances_by_join(_accesses(spark, sf_dir, "region_nations")[0]).select("step", "object_id", "object_bytes", "distance")


def _sweep_sql(name: str, layouts_: bool) -> str:
    d, acc = sql.distances(name)
    ours = f"SELECT 'bundle' AS layout, share, count(*)::BIGINT AS accesses, sum(CASE WHEN distance IS NOT NULL AND distance + byte_len <= body * share // 100 THEN 1 ELSE 0 END)::BIGINT AS hits, sum(CASE WHEN distance IS NOT NULL AND distance + byte_len <= body * share // 100 THEN 0 ELSE byte_len END)::BIGINT AS miss_bytes FROM ({d}), (SELECT sum(byte_len) AS body FROM ({sql.index(name)})), range(10, 101, 10) s(share) GROUP BY share"
    if not layouts_:
        return f"WITH {acc} {ours}"
    flat = f"SELECT layout, share, n_pairs AS accesses, 0::BIGINT AS hits, (dup_bytes + text_bytes)::BIGINT AS miss_bytes FROM ({sql.stats((name,))}), (VALUES ('loose'), ('pair_record')) l(layout), range(10, 101, 10) s(share)"
    return f"WITH {acc} {ours} UNION ALL {flat}"


@query(_sweep_sql("page_links", True))
def cache_sweep(spark, sf_dir):
    """Hits and missed bytes at ten capacities. Loose files and pair records share no object within an epoch: every access misses."""
    rows, idx = _accesses(spark, sf_dir, "page_links")
    body = idx.agg(F.sum("byte_len")).first()[0]
    ours = cachesim.sweep(cachesim.distances(rows), body).select(F.lit("bundle").alias("layout"), F.col("share").cast("long").alias("share"), "accesses", "hits", "miss_bytes")
    s = stats(spark, sf_dir, ("page_links",))
    shares = F.explode(F.array(*[F.lit(k).cast("long") for k in range(10, 101, 10)]))
    flat = s.withColumn("layout", F.explode(F.array(F.lit("loose"), F.lit("pair_record")))).withColumn("share", shares).select("layout", "share", F.col("n_pairs").alias("accesses"), F.lit(0).cast("long").alias("hits"), (F.col("dup_bytes") + F.col("text_bytes")).alias("miss_bytes"))
    return ours.union(flat)


@query(f"SELECT share, accesses, hits, miss_bytes FROM ({_sweep_sql('doc_cap5', False)})")
def cache_sweep_doc_cap5(spark, sf_dir):
    rows, idx = _accesses(spark, sf_dir, "doc_cap5")
    out = cachesim.sweep(cachesim.distances(rows), idx.agg(F.sum("byte_len")).first()[0])
    return out.select(F.col("share").cast("long").alias("share"), "accesses", "hits", "miss_bytes")


@query(f"SELECT 0::INTEGER AS worker, hits, miss_bytes FROM ({_sweep_sql('page_links', False)}) WHERE share = 50")
def lru_direct(spark, sf_dir):
    """The cache itself at half of the body, as a check of the distances."""
    rows, idx = _accesses(spark, sf_dir, "page_links")
    return cachesim.lru(rows, idx.agg(F.sum("byte_len")).first()[0] * 50 // 100)


@query(f"SELECT layout, accesses, miss_bytes FROM (SELECT unnest(['loose', 'path_table', 'pair_record', 'bundle']) AS layout, n_pairs AS accesses, unnest([dup_bytes + text_bytes, dup_bytes, dup_bytes + text_bytes, touched_bytes])::BIGINT AS miss_bytes FROM ({sql.stats(('page_links',))}))")
def zero_cache_reads(spark, sf_dir):
    d, t = F.col("dup_bytes"), F.col("text_bytes")
    rows = layouts.per_layout(stats(spark, sf_dir, ("page_links",)), {"loose": {"miss_bytes": d + t}, "path_table": {"miss_bytes": d}, "pair_record": {"miss_bytes": d + t}, "bundle": {"miss_bytes": F.col("touched_bytes")}})
    return rows.select("layout", F.col("n_pairs").alias("accesses"), "miss_bytes")


@query(f"SELECT corpus, share, round(share / 100 * (1 - n_bundles / n_pairs), 6) AS hit_share FROM ({sql.stats(SEVEN)}), range(10, 101, 10) s(share)")
def closed_form_hits(spark, sf_dir):
    s = stats(spark, sf_dir).withColumn("share", F.explode(F.array(*[F.lit(k).cast("long") for k in range(10, 101, 10)])))
    return s.select("corpus", "share", F.round(F.col("share") / 100 * (1 - F.col("n_bundles") / F.col("n_pairs")), 6).alias("hit_share"))


# Modelled rates. Media are scaled to the size of real images.

SCALE = 56


@query(f"SELECT corpus, layout, share, round(rate, 4) AS rate FROM ({sql.load_rate(SEVEN, SCALE)})")
def load_model(spark, sf_dir):
    return costs.load_rate(stats(spark, sf_dir), media_scale=SCALE).select("corpus", "layout", F.col("share").cast("long").alias("share"), F.round("rate", 4).alias("rate"))


@query(f"SELECT corpus, layout, round(rate, 4) AS rate FROM ({sql.write_rate(SEVEN, SCALE)})")
def write_model(spark, sf_dir):
    return costs.write_rate(stats(spark, sf_dir), media_scale=SCALE).select("corpus", "layout", F.round("rate", 4).alias("rate"))


_BEST = "SELECT corpus, round(max(CASE WHEN layout = 'bundle' THEN rate END), 4) AS ours, round(max(CASE WHEN layout <> 'bundle' THEN rate END), 4) AS best_baseline, round(max(CASE WHEN layout = 'bundle' THEN rate END) / max(CASE WHEN layout <> 'bundle' THEN rate END), 6) AS speedup FROM ({}) GROUP BY corpus"


@query(_BEST.format(f"SELECT corpus, layout, avg(rate) AS rate FROM ({sql.load_rate(SEVEN, SCALE)}) GROUP BY corpus, layout"))
def load_speedup_summary(spark, sf_dir):
    mean = compare.means(costs.load_rate(stats(spark, sf_dir), media_scale=SCALE)).withColumnRenamed("mean_of_rates", "rate")
    out = compare.vs_best(mean)
    return rounded(rounded(out, "speedup"), "ours", "best_baseline", digits=4)


@query(_BEST.format(sql.write_rate(SEVEN, SCALE)))
def write_speedup_summary(spark, sf_dir):
    return rounded(rounded(compare.vs_best(costs.write_rate(stats(spark, sf_dir), media_scale=SCALE)), "speedup"), "ours", "best_baseline", digits=4)


@query(f"SELECT corpus, layout, round(avg(rate), 4) AS mean_of_rates, round(1 / avg(1 / rate), 4) AS rate_of_mean_time FROM ({sql.load_rate(SEVEN, SCALE)}) GROUP BY corpus, layout")
def averaging_variants(spark, sf_dir):
    return rounded(compare.means(costs.load_rate(stats(spark, sf_dir), media_scale=SCALE)), "mean_of_rates", "rate_of_mean_time", digits=4)


@query(f"SELECT corpus, round(full_rate, 4) AS full_rate, round(1 - no_cache / full_rate, 6) AS drop_no_cache, round(1 - no_format / no_cache, 6) AS drop_no_format FROM (SELECT corpus, avg(rate) AS full_rate FROM ({sql.load_rate(SEVEN, SCALE)}) WHERE layout = 'bundle' GROUP BY corpus) JOIN (SELECT corpus, avg(CASE WHEN layout = 'bundle' THEN rate END) AS no_cache, avg(CASE WHEN layout = 'loose' THEN rate END) AS no_format FROM ({sql.load_rate(SEVEN, SCALE, cached=False)}) GROUP BY corpus) USING (corpus)")
def ablation(spark, sf_dir):
    s = stats(spark, sf_dir)
    out = compare.ablation(costs.load_rate(s, media_scale=SCALE), costs.load_rate(s, media_scale=SCALE, shares=(0,)))
    return rounded(out.select("corpus", F.round("full", 4).alias("full_rate"), "drop_no_cache", "drop_no_format"), "drop_no_cache", "drop_no_format")


@query(f"SELECT corpus, min(CASE WHEN a >= b THEN share END) AS share FROM (SELECT corpus, share, max(CASE WHEN layout = 'path_table' THEN rate END) AS a, max(CASE WHEN layout = 'pair_record' THEN rate END) AS b FROM ({sql.load_rate(SEVEN, SCALE)}) GROUP BY corpus, share) GROUP BY corpus")
def cache_crossover(spark, sf_dir):
    return compare.crossover(costs.load_rate(stats(spark, sf_dir), media_scale=SCALE)).select("corpus", F.col("share").cast("long").alias("share"))


@query(f"SELECT o.corpus, o.share, round(o.rate, 4) AS object_rate, round(p.rate, 4) AS pair_rate FROM ({sql.load_rate(SEVEN, SCALE)}) o JOIN ({sql.load_rate(SEVEN, SCALE, fetch='pair')}) p ON o.corpus = p.corpus AND o.share = p.share AND o.layout = p.layout WHERE o.layout = 'bundle'")
def fetch_granularity(spark, sf_dir):
    s = stats(spark, sf_dir)
    pick = lambda fetch, name: costs.load_rate(s, media_scale=SCALE, fetch=fetch).where("layout = 'bundle'").select("corpus", F.col("share").cast("long").alias("share"), F.round("rate", 4).alias(name))
    return pick("object", "object_rate").join(pick("pair", "pair_rate"), ["corpus", "share"])


_SCALES = (1, 4, 16, 64)


@query(" UNION ALL ".join(f"SELECT {k}::BIGINT AS media_scale, o.corpus, round(avg(o.rate), 4) AS object_rate, round(avg(p.rate), 4) AS pair_rate FROM ({sql.load_rate(('user_events', 'doc_cap5'), k)}) o JOIN ({sql.load_rate(('user_events', 'doc_cap5'), k, fetch='pair')}) p ON o.corpus = p.corpus AND o.share = p.share AND o.layout = p.layout WHERE o.layout = 'bundle' GROUP BY o.corpus" for k in _SCALES))
def size_ratio_sweep(spark, sf_dir):
    """Where whole-unit reads stop to pay: media of several sizes against texts that stay."""
    s, out = stats(spark, sf_dir, ("user_events", "doc_cap5")), None
    for k in _SCALES:
        mean = lambda fetch, name: costs.load_rate(s, media_scale=k, fetch=fetch).where("layout = 'bundle'").groupBy("corpus").agg(F.round(F.avg("rate"), 4).alias(name))  # noqa: B023, E731
        one = mean("object", "object_rate").join(mean("pair", "pair_rate"), "corpus").select(F.lit(k).cast("long").alias("media_scale"), "corpus", "object_rate", "pair_rate")
        out = one if out is None else out.union(one)
    return out


#: The seven training configurations; compute seconds of an epoch are ours, in proportion to trained parameters.
TRAINING = (("BLIP-Base", 224, 224, 1.0), ("BLIP-Large", 446, 446, 1.0), ("BLIP2-OPT2.7-F", 3700, 107, 1.0), ("BLIP2-OPT6.7-F", 7800, 108, 1.0), ("BLIP2-OPT2.7", 3700, 1100, 1.0), ("BLIP2-OPT2.7-GC", 3700, 1100, 1.3), ("BLIP2-OPT6.7-GC", 7800, 1100, 1.3))

#: All seven train on this data set, and doc_cap5 stands for it: compute seconds are of an epoch of so many pairs.
_EPOCH_PAIRS = next(p for n, _, p, _ in PUBLISHED if n == "MSCOCO")


@query(f"SELECT model, layout, round((compute_s + io_s * 0.5)::DOUBLE, 4) AS epoch_s FROM (SELECT model, layout, (600 + 0.5 * parameters + 1.5 * trained) * again * (n_pairs / {_EPOCH_PAIRS}) AS compute_s, n_pairs / rate AS io_s FROM (VALUES " + ", ".join(f"('{n}', {p}, {t}, {a})" for n, p, t, a in TRAINING) + f") m(model, parameters, trained, again), ({sql.load_rate(('doc_cap5',), SCALE)}) r WHERE share = 50 AND layout IN ('path_table', 'bundle'))")
def epoch_time_model(spark, sf_dir):
    """Epoch times by layout, with the input time of each layout on a corpus at half of the cache. Half of the input time is exposed to
    training, which the paper's setting leaves open. A model only."""
    entries = [F.struct(F.lit(n).alias("model"), F.lit(float(p)).alias("parameters"), F.lit(float(t)).alias("trained"), F.lit(a).alias("again")) for n, p, t, a in TRAINING]
    m = spark.range(1).select(F.inline(F.array(*entries)))
    rates = costs.load_rate(stats(spark, sf_dir, ("doc_cap5",)), media_scale=SCALE, shares=(50,)).where("layout IN ('path_table', 'bundle')")
    compute = (600 + 0.5 * F.col("parameters") + 1.5 * F.col("trained")) * F.col("again") * (F.col("n_pairs") / _EPOCH_PAIRS)
    rows = rates.join(F.broadcast(m)).select("model", "layout", compute.alias("compute_s"), (F.col("n_pairs") / F.col("rate") * 0.5).alias("io_s"))
    return costs.epoch_time(rows, overlap=False).select("model", "layout", F.round("epoch_s", 4).alias("epoch_s"))


@query(f"SELECT sample_id, bundle_id, text_pos, byte_offset, byte_len FROM ({sql.samples('doc_copies')})")
def converted_lookup(spark, sf_dir):
    """Flagship: convert the documents' copies, then find every sample by the index that the header asks for."""
    idx = index(spark, sf_dir, "doc_copies")
    return locate.locate(sampler.sample_ids(idx).select("sample_id"), idx, convert.classify(idx).first().asDict()).select(*locate.COLUMNS)
