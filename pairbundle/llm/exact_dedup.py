"""Exact deduplication by deterministic block naming.

Texts are cut into blocks of fixed size. Distinct blocks are sorted and their places in that order become integer names; pairs of
adjacent names are named the same way, level by level, until each document has one name. Equal names mean equal texts: nothing is
left to chance in naming. Block contents are shuffled once, after the map side has merged equal ones; occurrences travel as two hashes and find
their names through them. Should two contents share both hashes, these contents are named apart by a join on the contents.

Null texts count as empty, and an empty text has one empty block. Repeated rows are copies of each other like any equal texts. Null
doc_ids are rows like others, and rank below all others as keepers. An empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pairbundle.llm.common import doc_text, documents, staged, text_key, with_group_facts


def block_hashes(block: Column) -> tuple[Column, Column]:
    return F.xxhash64(block), F.xxhash64(F.lit(1), block)


def named(rows: DataFrame, columns: list[str], label: str) -> DataFrame:
    """Distinct values of the columns and an integer name for each: its place among the sorted values."""
    order = rows.select(*columns).distinct().sortWithinPartitions(*columns)
    return order.withColumn("name", F.monotonically_increasing_id())


def name_blocks(cut: DataFrame, hashes=block_hashes) -> DataFrame:
    """doc, txt, pos, blocks, block -> doc, txt, pos, blocks, name."""
    one, two = hashes(F.col("block"))
    cut = cut.withColumn("one", one).withColumn("two", two)
    lexicon = staged(named(cut, ["one", "two", "block"], "blocks").select("one", "two", "name"), "block-names")
    names = lexicon.groupBy("one", "two").agg(F.min("name").alias("name"), F.count("*").alias("contents"))
    found = cut.select("doc", "txt", "pos", "blocks", "one", "two").join(names, ["one", "two"]).select("doc", "txt", "pos", "blocks", "name")
    shared = staged(names.where("contents > 1").select("one", "two"), "shared-hashes", narrow=True)
    if shared.isEmpty():
        return found
    apart = cut.join(shared, ["one", "two"], "left_semi")
    renamed = apart.join(named(apart, ["block"], "shared").withColumn("name", -1 - F.col("name")), "block").select("doc", "txt", "pos", "blocks", "name")
    return cut.select("doc", "txt", "pos", "blocks", "one", "two").join(names.where("contents = 1"), ["one", "two"]).select("doc", "txt", "pos", "blocks", "name").union(renamed)


def identities(texts: DataFrame, block_bytes: int = 4096, hashes=block_hashes) -> DataFrame:
    """doc, txt -> the text's identity: its number of blocks and the name of them all.

    ``texts`` has doc, txt and data; doc is a document's key, txt a hash that tells rows of the same key apart."""
    count = F.greatest(F.lit(1), F.ceil(F.length("data") / block_bytes)).cast("int")
    parts = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda k: F.substring(F.col("data"), k * block_bytes + 1, F.lit(block_bytes)))
    cut = texts.withColumn("blocks", count).select("doc", "txt", "blocks", F.posexplode(parts).alias("pos", "block"))
    now = staged(name_blocks(cut, hashes), "names", narrow=True)
    done, width = now.where("blocks = 1").select("doc", "txt", "blocks", "name"), now.agg(F.max("blocks")).first()[0] or 1
    out, reach = [done], 1
    now = now.where("blocks > 1")
    while reach < width:
        reach *= 2
        even = F.pmod("pos", F.lit(2)) == 0
        paired = now.groupBy("doc", "txt", "blocks", F.floor(F.col("pos") / 2).cast("int").alias("pos")).agg(F.max(F.when(even, F.col("name"))).alias("a"), F.coalesce(F.max(F.when(~even, F.col("name"))), F.lit(-(2**63))).alias("b"))
        paired = staged(paired, "pairs", narrow=True)
        now = staged(paired.join(named(paired, ["a", "b"], "pairs"), ["a", "b"]).select("doc", "txt", "pos", "blocks", "name"), "names", narrow=True)
        out.append(now.where((F.col("blocks") <= reach) & (F.col("blocks") > reach // 2)).select("doc", "txt", "blocks", "name"))
        now = now.where(F.col("blocks") > reach)
    whole = out[0]
    for more in out[1:]:
        whole = whole.union(more)
    return whole.distinct()


def exact_groups(docs: DataFrame, block_bytes: int = 4096, **options) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 and text_key (its bytes) of every row; of equal texts the row with the largest doc_id
    stays. Rows with the same doc_id and text are one document to this rule: all are marked alike. A document's row and its identity meet
    by doc_id and SHA-256, so that rows of one doc_id, or of none, are told apart."""
    rows = doc_text(docs)
    key = [F.coalesce("doc_id", F.lit(-(2**63))).alias("doc"), text_key().alias("txt")]
    names = identities(rows.select(*key, F.col("text").cast("binary").alias("data")), block_bytes, **options)
    light = rows.select(*key, "doc_id")
    marked = staged(light.join(names, ["doc", "txt"]).drop("doc").withColumnRenamed("txt", "text_key"), "identities", narrow=True)
    groups = marked.groupBy("blocks", "name").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
    out = with_group_facts(marked, staged(groups, "groups", narrow=True), ["blocks", "name"], "group_size")
    return out.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("text_key")).alias("text_sha256"), "text_key")


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_groups(documents(spark, sf_dir)).drop("text_key")


ORACLE_OP10 = """
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY t)
SELECT d.doc_id, g.keep_id, g.group_size, d.doc_id = g.keep_id AS kept, sha256(d.t) AS text_sha256 FROM d JOIN g ON d.t = g.t
"""
