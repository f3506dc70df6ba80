"""Near-duplicates by SimHash with tiled exact comparison.

Fingerprints of 64 bits over word shingles; equal ones collapse first, so copies cost nothing later. Two fingerprints within radius r
agree on at least k - r of any k disjoint bit blocks, so every link shows between rows that agree on one choice of k - r blocks. The
rows of such a choice form a group, sorted by bit count and compared in tiles with exclusive-or and bit counts; tile pairs whose bit
counts differ beyond the radius are skipped. A group beyond ``tile`` rows is dealt to many tasks as pairs of tiles. Every tile pair
reports a spanning forest of its links, never all pairs, and components follow by minimum labels with pointer jumping.

Null texts count as empty. Texts without words have fingerprint zero and link like any other. Repeated rows and equal doc_ids keep all
their rows. An empty table gives an empty table. Null doc_ids take part, and a component of only null doc_ids has a null id.
"""

from __future__ import annotations

from itertools import accumulate, combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairbundle.llm.common import doc_text, documents, staged, text_key, with_group_facts


def fingerprint(raw: bytes, width: int = 4, seed: int = 42) -> int:
    """The SimHash of one text: bit j is set if it is set in over half of the shingle hashes, repeats included."""
    import xxhash

    words = raw.lower().split()  # of bytes: A-Z and ASCII white space only
    if not words:
        return 0
    if len(words) <= width:
        return xxhash.xxh64_intdigest(b" ".join(words), seed)
    digest, text = xxhash.xxh64_intdigest, b" ".join(words)
    ends = list(accumulate(len(w) + 1 for w in words))
    hashes = np.array([digest(text[a : b - 1], seed) for a, b in zip([0, *ends], ends[width - 1 :])], np.uint64)
    ones = sum(np.unpackbits(hashes[k : k + 65536].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64) for k in range(0, len(hashes), 65536))
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, width: int = 4) -> DataFrame:
    """doc_id, text_key (SHA-256 of the text) and the fingerprint as a signed long."""

    def run(batches):
        for batch in batches:
            marks = np.array([fingerprint(t, width) for t in batch.column(2).to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(marks.view(np.int64))], ["doc_id", "text_key", "fp"])

    return docs.select("doc_id", text_key().alias("text_key"), F.col("text").cast("binary").alias("text")).mapInArrow(run, "doc_id long, text_key binary, fp long")


def block_masks(blocks: int, radius: int) -> list[int]:
    """Bit masks, one for each choice of ``blocks - radius`` of that many even blocks of 64 bits, as signed longs."""
    edges = [64 * k // blocks for k in range(blocks + 1)]
    single = [((1 << (b - a)) - 1) << a for a, b in zip(edges, edges[1:])]
    masks = [sum(c) for c in combinations(single, blocks - radius)]
    return [m - (1 << 64) if m >= 1 << 63 else m for m in masks]


def blocks_for(n: int) -> int:
    """So many blocks that a group holds few of n distinct fingerprints; results don't depend on it."""
    return 5 if n < 1 << 21 else 6 if n < 1 << 27 else 7 if n < 1 << 33 else 8


def forest(a: np.ndarray, b: np.ndarray | None, radius: int, step: int = 512) -> tuple[np.ndarray, np.ndarray]:
    """Edges that connect what the links within ``a``, or between ``a`` and ``b``, connect; no more than some times the rows."""
    a = a[np.argsort(np.bitwise_count(a), kind="stable")]
    other = a if b is None else b[np.argsort(np.bitwise_count(b), kind="stable")]
    ones, others = np.bitwise_count(a).astype(np.int16), np.bitwise_count(other).astype(np.int16)
    us, vs = [], []
    for k in range(0, len(a), step):
        rows = a[k : k + step]
        lo = np.searchsorted(others, ones[k] - radius, "left")
        hi = np.searchsorted(others, ones[min(k + step, len(a)) - 1] + radius, "right")
        lo = max(lo, k) if b is None else lo
        for m in range(lo, hi, 8192):
            cols = other[m : min(m + 8192, hi)]
            near = np.bitwise_count(rows[:, None] ^ cols[None, :]) <= radius
            if np.count_nonzero(near) <= 4 * (len(rows) + len(cols)):
                i, j = np.nonzero(near)
                us.append(rows[i])
                vs.append(cols[j])
            else:  # dense: each column keeps its first row; rows that share a column follow from merging along the columns
                label = np.arange(len(rows))
                while True:
                    col = np.where(near, label[:, None], len(rows)).min(0)
                    new = np.minimum(label, np.where(near, col[None, :], len(rows)).min(1))
                    if (new == label).all():
                        break
                    label = new
                own = col < len(rows)
                us += [rows[np.minimum(label, len(rows) - 1)], rows[col[own]]]
                vs += [rows, cols[own]]
    u, v = (np.concatenate(x) if x else np.zeros(0, np.uint64) for x in (us, vs))
    return u[u != v], v[u != v]


def tile_links(marks: DataFrame, radius: int = 4, tile: int = 8192, blocks: int | None = None) -> DataFrame:
    """Links u, v of a forest over distinct fingerprints ``fp`` within the radius."""
    blocks = blocks or blocks_for(marks.count())
    masks = block_masks(blocks, radius)
    cells = marks.select("fp", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(m)) for m in masks])).alias("choice", "part"))
    sizes = cells.groupBy("choice", "part").count()
    large = sizes.where(F.col("count") > tile).withColumn("tiles", F.ceil(F.col("count") / tile).cast("int")).drop("count")
    cells = cells.join(large, ["choice", "part"], "left").fillna({"tiles": 1})
    ones, salt = F.expr("bit_count(fp)"), F.pmod(F.xxhash64("fp", F.lit(7)), F.col("tiles")).cast("int")
    # Tiles of a large group: bit count and salt. A row meets its own tile and all tiles whose bit counts are within the radius.
    pairs = F.explode(F.expr(f"flatten(transform(sequence(greatest(0, ones - {radius}), least(64, ones + {radius})), o -> transform(sequence(0, tiles - 1), s -> o * tiles + s)))"))
    small = cells.where("tiles = 1").select("choice", "part", F.lit(0).alias("t1"), F.lit(0).alias("t2"), F.lit(0).alias("mine"), "fp")
    big = cells.where("tiles > 1").withColumn("ones", ones).withColumn("mine", F.col("ones") * F.col("tiles") + salt).select("choice", "part", "mine", "fp", pairs.alias("other"))
    big = big.select("choice", "part", F.least("mine", "other").alias("t1"), F.greatest("mine", "other").alias("t2"), "mine", "fp")

    def compare(batches):
        held: list = []
        key = None

        def links():
            mine, fp = (np.concatenate(x) for x in zip(*held))
            a, b = fp[mine == key[2]], fp[mine != key[2]]
            if key[2] == key[3]:
                return forest(a, None, radius)
            return forest(a, b, radius) if len(a) and len(b) else (a[:0], a[:0])

        def batch_of(u, v):
            return pa.RecordBatch.from_arrays([pa.array(x.view(np.int64)) for x in (u, v)], ["u", "v"])

        for batch in batches:
            c = [x.to_numpy(zero_copy_only=False) for x in batch.columns]
            if not len(c[0]):
                continue
            new = np.ones(len(c[0]), bool)
            new[1:] = (c[0][1:] != c[0][:-1]) | (c[1][1:] != c[1][:-1]) | (c[2][1:] != c[2][:-1]) | (c[3][1:] != c[3][:-1])
            at = np.flatnonzero(new)
            us, vs = [], []
            for a, b in zip(at.tolist(), [*at[1:].tolist(), len(new)]):
                now = (int(c[0][a]), int(c[1][a]), int(c[2][a]), int(c[3][a]))
                if key is not None and now != key:
                    if sum(len(x[0]) for x in held) > 1:
                        u, v = links()
                        us.append(u)
                        vs.append(v)
                    held = []
                key = now
                held.append((c[4][a:b], c[5][a:b].view(np.uint64)))
            if us:
                yield batch_of(np.concatenate(us), np.concatenate(vs))
        if held:
            yield batch_of(*links())

    rows = small.unionByName(big).repartition("choice", "part", "t1", "t2").sortWithinPartitions("choice", "part", "t1", "t2")
    return rows.select("choice", "part", "t1", "t2", "mine", "fp").mapInArrow(compare, "u long, v long").distinct()


def components(links: DataFrame, most: int = 64) -> DataFrame:
    """node and label, the least node that links lead to. Every round is a written table; rounds end when no label moves."""
    both = staged(links.union(links.select("v", "u")).distinct(), "links", narrow=True)
    labels = staged(both.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("m")).select("node", F.least("node", "m").alias("label"), F.lit(True).alias("moved")), "labels", narrow=True)
    for _ in range(most):
        near = both.join(labels.select(F.col("node").alias("v"), "label"), "v").groupBy(F.col("u").alias("node")).agg(F.min("label").alias("m"))
        least = labels.select("node", F.col("label").alias("was")).join(near, "node", "left").select("node", "was", F.least("was", "m").alias("label"))
        jump = labels.select(F.col("node").alias("label"), F.col("label").alias("up"))
        new = least.join(jump, "label", "left").select("node", F.least("label", "up").alias("label"), "was")
        labels = staged(new.select("node", "label", (F.col("label") != F.col("was")).alias("moved")), "labels", narrow=True)
        if labels.where("moved").isEmpty():
            return labels.select("node", "label")
    raise RuntimeError("labels still move")


def labelled_rows(docs: DataFrame, width: int = 4, radius: int = 4, **options) -> DataFrame:
    """doc_id, fingerprint, component_id, text_key and label of every row. The label alone tells components apart: least doc_ids may repeat."""
    marked = staged(fingerprints(doc_text(docs), width), "fingerprints")
    distinct = staged(marked.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count("*").alias("rows")), "distinct-fingerprints", narrow=True)
    labels = components(tile_links(distinct.select("fp"), radius, **options))
    named = distinct.join(labels.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", "rows", F.coalesce("label", "fp").alias("label"))
    ids = named.groupBy("label").agg(F.min("least").alias("component_id"))
    classes = staged(named.join(ids, "label").select("fp", "rows", "component_id", "label"), "classes", narrow=True)
    return with_group_facts(marked, classes, ["fp"], "rows").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "text_key", "label")


def near_duplicates(docs: DataFrame, width: int = 4, radius: int = 4, **options) -> DataFrame:
    """doc_id, fingerprint, component_id and text_key of every row."""
    return labelled_rows(docs, width, radius, **options).drop("label")


def op4_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(documents(spark, sf_dir)).drop("text_key")
