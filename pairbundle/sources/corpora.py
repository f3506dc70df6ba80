"""Pair corpora derived from the given tables: pair_ord, media, text, src_id. A null text is a media object without texts."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("long").cast("string")


def _day(c: str) -> Column:
    return F.date_format(c, "yyyy-MM-dd")


def _packed(*parts) -> Column:
    return F.concat_ws("|", *[F.col(p).cast("string") if isinstance(p, str) else p for p in parts])


def order_text() -> Column:
    return _packed("o_orderkey", "o_custkey", "o_orderstatus", _cents("o_totalprice"), _day("o_orderdate"), "o_orderpriority")


def lineitem_text() -> Column:
    return _packed("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.round("l_quantity").cast("long").cast("string"), _cents("l_extendedprice"), _cents("l_discount"), _cents("l_tax"), "l_returnflag", "l_linestatus", _day("l_shipdate"))


def customer_text() -> Column:
    return _packed("c_custkey", "c_name", "c_nationkey", _cents("c_acctbal"), "c_mktsegment")


def supplier_text() -> Column:
    return _packed("s_suppkey", "s_name", "s_nationkey", _cents("s_acctbal"))


def part_text() -> Column:
    return _packed("p_partkey", "p_name", "p_brand", "p_type", "p_size", _cents("p_retailprice"))


def lineitem_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lineitems as texts, with an order that all columns decide: the table has no key."""
    rows = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", lineitem_text().alias("text"))
    rank = F.row_number().over(Window.partitionBy("l_orderkey").orderBy("text"))
    return rows.withColumn("pair_ord", F.col("l_orderkey") * 1000 + rank)


def _distinct_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").groupBy(F.col("text").alias("media")).agg(F.min("doc_id").alias("src_id"))


def captions(spark: SparkSession, sf_dir: str, count: int | None, width: int) -> DataFrame:
    """Slices of each distinct text as its captions; ``count`` None: one, and one more for each of the length modulo 25."""
    n = F.length("media")
    k = F.lit(count) if count else 1 + n % 25
    each = _distinct_texts(spark, sf_dir).withColumn("k", k.cast("long")).withColumn("j", F.explode(F.sequence(F.lit(1).cast("long"), F.col("k"))))
    start = (1 + F.floor((F.col("j") - 1) * n / F.col("k"))).cast("int")
    return each.select((F.col("src_id") * 1000 + F.col("j")).alias("pair_ord"), "media", F.concat(F.col("j").cast("string"), F.lit(":"), F.substring("media", start, F.lit(width))).alias("text"), "src_id")


def region_nations(spark, sf_dir):
    n, r = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    return n.join(r, n.n_regionkey == r.r_regionkey).select(F.col("n_nationkey").cast("long").alias("pair_ord"), F.col("r_name").alias("media"), F.col("n_name").alias("text"), F.col("n_nationkey").cast("long").alias("src_id"))


def page_links(spark, sf_dir):
    p = table(spark, sf_dir, "pages").select("page_id", "html", F.posexplode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), F.lit(1))).alias("pos", "text"))
    return p.select((F.col("page_id") * 1000 + F.col("pos") + 1).alias("pair_ord"), F.col("html").alias("media"), "text", F.col("page_id").alias("src_id"))


def orders_lineitems(spark, sf_dir, keep_childless: bool = False):
    o = table(spark, sf_dir, "orders").select("o_orderkey", order_text().alias("media"))
    l = lineitem_pairs(spark, sf_dir)  # noqa: E741
    rows = o.join(l, o.o_orderkey == l.l_orderkey, "left" if keep_childless else "inner")
    return rows.select(F.coalesce("pair_ord", F.col("o_orderkey") * 1000).alias("pair_ord"), "media", "text", F.col("o_orderkey").alias("src_id"))


def customer_orders(spark, sf_dir):
    c = table(spark, sf_dir, "customer").select("c_custkey", customer_text().alias("media"))
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", order_text().alias("text"))
    return o.join(c, o.o_custkey == c.c_custkey).select(F.col("o_orderkey").alias("pair_ord"), "media", "text", F.col("o_orderkey").alias("src_id"))


def part_lineitems(spark, sf_dir):
    p = table(spark, sf_dir, "part").select("p_partkey", part_text().alias("media"))
    return lineitem_pairs(spark, sf_dir).join(p, F.col("l_partkey") == F.col("p_partkey")).select("pair_ord", "media", "text", F.col("p_partkey").alias("src_id"))


def supplier_lineitems(spark, sf_dir):
    s = table(spark, sf_dir, "supplier").select("s_suppkey", supplier_text().alias("media"))
    return lineitem_pairs(spark, sf_dir).join(s, F.col("l_suppkey") == F.col("s_suppkey")).select("pair_ord", "media", "text", F.col("s_suppkey").alias("src_id"))


def user_events(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    return e.select(F.col("event_id").alias("pair_ord"), F.concat(F.lit("user-"), F.col("user_id").cast("string")).alias("media"), _packed("event_id", "event_type", "props").alias("text"), F.col("event_id").alias("src_id"))


def conv_turns(spark, sf_dir):
    c = table(spark, sf_dir, "conversations")
    said = F.array_sort(F.collect_list(F.when(F.col("role") == "assistant", F.struct("turn", "text"))))
    media = c.groupBy("conv_id").agg(F.array_join(F.transform(said, lambda x: x["text"]), "\n").alias("media"), F.max((F.col("role") == "assistant").cast("int")).alias("some")).where("some = 1")
    return c.where("role <> 'assistant'").join(media, "conv_id").select((F.col("conv_id") * 1000 + F.col("turn")).alias("pair_ord"), "media", "text", F.col("conv_id").alias("src_id"))


def doc_copies(spark, sf_dir):
    d = table(spark, sf_dir, "documents")
    return d.select(F.col("doc_id").alias("pair_ord"), F.col("text").alias("media"), F.concat_ws("/", "source", "lang", F.col("doc_id").cast("string")).alias("text"), F.col("doc_id").alias("src_id"))


def doc_labels(spark, sf_dir):
    d, l = table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "labels")  # noqa: E741
    return d.join(l, "doc_id").select(F.col("doc_id").alias("pair_ord"), F.col("text").alias("media"), F.concat(F.lit("q"), F.col("quality").cast("string"), F.lit("t"), F.col("toxic").cast("string")).alias("text"), F.col("doc_id").alias("src_id"))


def bench_hits(spark, sf_dir):
    """Documents that contain a benchmark item. Candidates share three whole words from inside the item, in a row; then the item is looked for."""
    d, b = table(spark, sf_dir, "documents").select("doc_id", F.col("text").alias("media")), table(spark, sf_dir, "benchmark")
    words = lambda c: F.filter(F.split(c, r"\s+"), lambda w: w != "")
    triples = lambda w: F.when(F.size(w) > 2, F.transform(F.sequence(F.lit(1), F.size(w) - 2), lambda i: F.xxhash64(F.slice(w, i, 3)))).otherwise(F.array().cast("array<bigint>"))
    inner = words("text")
    long = b.where(F.size(inner) >= 5).select("item_id", "text", F.xxhash64(F.slice(inner, 2, 3)).alias("key"))
    short = b.where(F.size(inner) < 5).select("item_id", "text")
    keyed = d.select("doc_id", "media", words("media").alias("w")).select("doc_id", "media", F.explode(F.array_distinct(triples(F.col("w")))).alias("key"))
    hits = keyed.join(long, "key").where(F.contains("media", F.col("text"))).select("doc_id", "media", "item_id", "text")
    rest = d.join(short, F.contains(d["media"], short["text"])).select("doc_id", "media", "item_id", "text")
    return hits.union(rest).select((F.col("doc_id") * 1000 + F.col("item_id")).alias("pair_ord"), "media", "text", F.col("doc_id").alias("src_id"))


def pages_url(spark, sf_dir):
    return table(spark, sf_dir, "pages").select(F.col("page_id").alias("pair_ord"), F.col("html").alias("media"), F.col("url").alias("text"), F.col("page_id").alias("src_id"))


def vector_text() -> Column:
    return F.array_join(F.transform("embedding", lambda x: F.round(x.cast("double") * 1000000).cast("long").cast("string")), ",")


def vec_label(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("pair_ord"), vector_text().alias("media"), F.col("label").cast("string").alias("text"), F.col("vec_id").alias("src_id"))


def _uni(df: DataFrame, key: str, media: Column) -> DataFrame:
    return df.groupBy(media.alias("media")).agg(F.min(key).alias("src_id")).select(F.col("src_id").alias("pair_ord"), "media", F.lit(None).cast("string").alias("text"), "src_id")


CORPORA: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "region_nations": region_nations,
    "doc_cap5": lambda s, d: captions(s, d, 5, 60),
    "doc_cap20": lambda s, d: captions(s, d, 20, 48),
    "doc_caphyb": lambda s, d: captions(s, d, None, 48),
    "page_links": page_links,
    "orders_lineitems": orders_lineitems,
    "customer_orders": customer_orders,
    "part_lineitems": part_lineitems,
    "supplier_lineitems": supplier_lineitems,
    "user_events": user_events,
    "conv_turns": conv_turns,
    "doc_copies": doc_copies,
    "doc_labels": doc_labels,
    "bench_hits": bench_hits,
    "pages_url": pages_url,
    "vec_label": vec_label,
    "docs_uni": lambda s, d: _uni(table(s, d, "documents"), "doc_id", F.col("text")),
    "bench_uni": lambda s, d: _uni(table(s, d, "benchmark"), "item_id", F.col("text")),
    "vec_uni": lambda s, d: _uni(table(s, d, "embeddings"), "vec_id", vector_text()),
}

#: The corpora that stand for the seven data sets of the storage and loading experiments.
SEVEN = ("doc_cap5", "doc_cap20", "doc_caphyb", "page_links", "conv_turns", "orders_lineitems", "pages_url")


def corpus(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return CORPORA[name](spark, sf_dir)
