"""Mixing sources to target weights by temperature.

Token shares of sources are raised to an exponent and normalised. The exponent is bisected, five halvings in each aggregation over the
sources, until the weights' entropy meets a target or no source repeats beyond a limit. Weights become token budgets. A source's
documents lie in blocks by a hash; every pass through the source takes the blocks in another order, and the last pass stops where the
budget ends, within one document of it. Rows are never gathered by source: windows run over at most ``most_blocks`` block totals of a
source, or over the documents of the one block in which a budget ends.

Tokens are runs of characters other than ASCII white space. A null source counts as the source named by an empty string, a null text
as empty. A document without tokens costs nothing and is taken once in each pass of its block. A source without any tokens is taken
once. Equal doc_ids share their block and order. An empty table gives an empty table.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pairbundle.llm.common import documents, staged

WORDS = r"[^\x20\x09-\x0D]+"


def hashed(*parts) -> Column:
    """A non-negative 32-bit number from the md5 of the parts, joined by bars."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("long")


def named_source() -> Column:
    return F.coalesce(F.col("source").cast("string"), F.lit(""))


def counted(docs: DataFrame) -> DataFrame:
    """doc_id, source and n_tokens of every row."""
    n_tokens = F.regexp_count(F.coalesce("text", F.lit("")), F.lit(WORDS)).cast("long")
    return docs.select("doc_id", named_source().alias("source"), n_tokens.alias("n_tokens"))


def _measures(sources: DataFrame, exponents: list[float]) -> list[tuple[float, float]]:
    """Entropy of the weights, and the largest repetition of a source when every source is taken in full at least once."""
    share, aggregates = F.col("share"), []
    for k, a in enumerate(exponents):
        raised = F.pow(share, F.lit(a))
        aggregates += [F.sum(raised).alias(f"z{k}"), F.sum(raised * F.log(share)).alias(f"e{k}"), F.max(raised / share).alias(f"h{k}"), F.min(raised / share).alias(f"l{k}")]
    row = sources.agg(*aggregates).first()
    return [(math.log(row[f"z{k}"]) - a * row[f"e{k}"] / row[f"z{k}"], row[f"h{k}"] / row[f"l{k}"]) for k, a in enumerate(exponents)]


def temperature(sources: DataFrame, entropy: float | None = None, repetition: float | None = None, halvings: int = 20, at_once: int = 5) -> float:
    """The largest exponent (mildest change) whose entropy reaches the target, a share of the greatest possible one; or the least
    exponent (strongest change) under which no source repeats more than ``repetition`` times as often as another."""
    n = sources.count()
    if n < 2:
        return 1.0
    fits = (lambda m: m[0] >= entropy * math.log(n) - 1e-12) if entropy is not None else (lambda m: m[1] <= repetition)
    k = 0
    steps = 1 << at_once
    if entropy is not None:  # fits from zero up to some exponent
        if fits(_measures(sources, [1.0])[0]):
            return 1.0
        for depth in range(at_once, halvings + 1, at_once):
            k *= steps
            k += max(j for j, m in enumerate(_measures(sources, [(k + j) / (1 << depth) for j in range(steps)])) if j == 0 or fits(m))
        return k / (1 << halvings)
    k = 1  # fits from some exponent up to one
    for depth in range(at_once, halvings + 1, at_once):
        k *= steps
        k -= max(j for j, m in enumerate(_measures(sources, [(k - j) / (1 << depth) for j in range(steps)])) if j == 0 or fits(m))
    return k / (1 << halvings)


def schedule(docs: DataFrame, entropy: float | None = 0.95, repetition: float | None = None, budget: int | None = None, seed: int = 17, block_tokens: int = 20_000, most_blocks: int = 4096) -> DataFrame:
    """A row for each time that a document is taken: doc_id, source, n_tokens, weight, pass_no, block, block_rank.

    ``budget`` is the number of tokens to take; by default, the least with which every source is taken in full at least once."""
    rows = staged(counted(docs), "counted")
    totals = staged(rows.groupBy("source").agg(F.sum("n_tokens").alias("tokens")), "sources", narrow=True)
    total = totals.agg(F.sum("tokens")).first()[0] or 0
    sources = totals.where("tokens > 0").withColumn("share", F.col("tokens") / F.lit(float(max(total, 1))))
    alpha = temperature(sources, entropy if repetition is None else None, repetition) if total else 1.0
    raised = sources.withColumn("raised", F.pow("share", F.lit(alpha)))
    norm, cover = raised.agg(F.sum("raised"), F.max(F.col("tokens") / F.col("raised"))).first()
    weighted = raised.select("source", "tokens", (F.col("raised") / F.lit(norm or 1.0)).alias("weight"))
    take = float(budget) if budget is not None else float((cover or 0.0) * (norm or 1.0))
    quota = F.round(F.col("weight") * F.lit(take)).cast("long")
    plan = weighted.withColumn("quota", quota).unionByName(totals.where("tokens = 0").select("source", "tokens", F.lit(0.0).alias("weight"), F.lit(0).cast("long").alias("quota")))
    plan = plan.withColumn("full", F.when(F.col("tokens") == 0, 1).otherwise(F.floor(F.col("quota") / F.greatest("tokens", F.lit(1)))).cast("int")).withColumn("rest", F.when(F.col("tokens") == 0, 0).otherwise(F.col("quota") - F.col("full") * F.col("tokens")).cast("long"))
    plan = staged(plan.withColumn("blocks", F.greatest(F.lit(1), F.least(F.lit(most_blocks), F.ceil(F.col("tokens") / block_tokens))).cast("int")), "plan", narrow=True)
    doc = F.coalesce(F.col("doc_id").cast("string"), F.lit(""))
    placed = rows.join(plan.select("source", "blocks"), "source").select("doc_id", "source", "n_tokens", F.pmod(hashed(F.lit("block"), F.lit(seed), doc), F.col("blocks")).cast("int").alias("block"))
    sums = placed.groupBy("source", "block").agg(F.sum("n_tokens").alias("size")).join(plan, "source")
    turns = sums.select("source", "block", "size", "weight", "full", "rest", F.explode(F.sequence(F.lit(1), F.col("full") + F.when(F.col("rest") > 0, 1).otherwise(F.when(F.col("full") == 0, 1).otherwise(0)))).alias("pass_no"))
    order = Window.partitionBy("source", "pass_no").orderBy(hashed(F.lit("order"), F.lit(seed), "source", "pass_no", "block"), "block")
    turns = turns.withColumn("block_rank", F.row_number().over(order)).withColumn("before", F.coalesce(F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    room = F.col("rest") - F.col("before")
    turns = turns.withColumn("room", F.when(F.col("pass_no") <= F.col("full"), F.col("size")).otherwise(room)).where("room > 0 OR (size = 0 AND pass_no <= full)")
    taken = placed.join(turns.select("source", "block", "size", "weight", "pass_no", "block_rank", "room"), ["source", "block"])
    inside = Window.partitionBy("source", "pass_no").orderBy(hashed(F.lit("inside"), F.lit(seed), doc), "doc_id", "n_tokens").rowsBetween(Window.unboundedPreceding, -1)
    ends = taken.where("room < size").withColumn("ahead", F.coalesce(F.sum("n_tokens").over(inside), F.lit(0))).where("ahead < room").drop("ahead")
    both = taken.where("room >= size").unionByName(ends)
    return both.select("doc_id", "source", "n_tokens", F.round("weight", 9).alias("weight"), "pass_no", "block", "block_rank")


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The documents' rows, each as often as the schedule takes it. A row is known by its doc_id, source and number of tokens; rows that
    agree in all three stand in one place of every pass and share their copies."""
    keys = ["doc_id", "source", "n_tokens"]
    copies = schedule(docs, **options).groupBy(*keys, "pass_no").count().groupBy(*keys).agg(F.count("*").cast("int").alias("_pb_copies"))
    columns = docs.columns
    copies = copies.select(F.col("doc_id").alias("_pb_doc"), F.col("source").alias("_pb_source"), F.col("n_tokens").alias("_pb_tokens"), "_pb_copies")
    n_tokens = F.regexp_count(F.coalesce("text", F.lit("")), F.lit(WORDS)).cast("long")
    same = F.col("doc_id").eqNullSafe(F.col("_pb_doc")) & (named_source() == F.col("_pb_source")) & (n_tokens == F.col("_pb_tokens"))
    keyed = docs.join(copies, same)
    return keyed.withColumn("_pb_turn", F.explode(F.sequence(F.lit(1), F.col("_pb_copies")))).select(*columns)


def op1_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return schedule(documents(spark, sf_dir))


def _step(before: str, depth: int) -> str:
    """One aggregation's five halvings: the largest step whose entropy reaches the target."""
    a = f"(({before} * 32 + j) / {1 << depth}::DOUBLE)"
    return f"(SELECT max(k) FROM (SELECT {before} * 32 + j AS k, j, ln(sum(pow(share, {a}))) - any_value({a}) * sum(pow(share, {a}) * ln(share)) / sum(pow(share, {a})) AS h FROM s, range(32) r(j) GROUP BY j) WHERE j = 0 OR h >= (SELECT 0.95::DOUBLE * ln(count(*)) - 1e-12 FROM s))"


_HASH = "('0x' || substr(md5({}), 1, 8))::BIGINT"

ORACLE_OP1 = f"""
WITH c AS (SELECT doc_id, coalesce(source, '') AS source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS n_tokens FROM documents),
t AS (SELECT source, sum(n_tokens)::BIGINT AS tokens FROM c GROUP BY 1),
s AS (SELECT source, tokens, tokens / (SELECT sum(tokens) FROM t)::DOUBLE AS share FROM t WHERE tokens > 0),
k1 AS (SELECT {_step("0", 5)} AS k), k2 AS (SELECT {_step("(SELECT k FROM k1)", 10)} AS k), k3 AS (SELECT {_step("(SELECT k FROM k2)", 15)} AS k), k4 AS (SELECT {_step("(SELECT k FROM k3)", 20)} AS k),
a AS (SELECT CASE WHEN count(*) < 2 OR -sum(share * ln(share)) / sum(share) + ln(sum(share)) >= 0.95::DOUBLE * ln(count(*)) - 1e-12 THEN 1::DOUBLE ELSE (SELECT k FROM k4) / {1 << 20}::DOUBLE END AS alpha FROM s),
r AS (SELECT source, tokens, pow(share, alpha) AS raised FROM s, a),
w AS (SELECT source, tokens, raised / (SELECT sum(raised) FROM r) AS weight, round(raised / (SELECT sum(raised) FROM r) * ((SELECT max(tokens / raised) FROM r) * (SELECT sum(raised) FROM r)))::BIGINT AS quota FROM r UNION ALL SELECT source, tokens, 0, 0 FROM t WHERE tokens = 0),
p AS (SELECT source, weight, CASE WHEN tokens = 0 THEN 1 ELSE quota // greatest(tokens, 1) END AS whole, CASE WHEN tokens = 0 THEN 0 ELSE quota % greatest(tokens, 1) END AS rest, greatest(1, least(4096, ceil(tokens / 20000)))::BIGINT AS blocks FROM w),
d AS (SELECT c.*, {_HASH.format("'block|17|' || coalesce(doc_id::VARCHAR, '')")} % blocks AS block FROM c JOIN p ON c.source = p.source),
b AS (SELECT source, block, sum(n_tokens)::BIGINT AS size FROM d GROUP BY 1, 2),
u AS (SELECT b.source, b.block, b.size, p.weight, p.whole, p.rest, pass_no FROM b JOIN p ON b.source = p.source, range(1, 1000) x(pass_no) WHERE pass_no <= whole + CASE WHEN rest > 0 OR whole = 0 THEN 1 ELSE 0 END),
o AS (SELECT *, row_number() OVER v AS block_rank, coalesce(sum(size) OVER (v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM u WINDOW v AS (PARTITION BY source, pass_no ORDER BY {_HASH.format("'order|17|' || source || '|' || pass_no || '|' || block")}, block)),
m AS (SELECT *, CASE WHEN pass_no <= whole THEN size ELSE rest - before END AS room FROM o),
j AS (SELECT d.doc_id, d.source, d.n_tokens, m.weight, m.pass_no, m.block, m.block_rank, m.room, m.size FROM d JOIN m ON d.source = m.source AND d.block = m.block WHERE room > 0 OR (size = 0 AND pass_no <= whole)),
e AS (SELECT *, coalesce(sum(n_tokens) OVER (PARTITION BY source, pass_no ORDER BY {_HASH.format("'inside|17|' || coalesce(doc_id::VARCHAR, '')")}, doc_id, n_tokens ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead FROM j WHERE room < size)
SELECT doc_id, source, n_tokens, round(weight, 9) AS weight, pass_no::INTEGER AS pass_no, block::INTEGER AS block, block_rank::INTEGER AS block_rank FROM (SELECT * FROM j WHERE room >= size UNION ALL SELECT * EXCLUDE (ahead) FROM e WHERE ahead < room)
"""
