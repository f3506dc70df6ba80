"""Exact reuse of a byte-capacity cache with least-recent eviction, from recency distances.

``accesses`` has worker, step (unique within the worker), object_id and object_bytes. An access hits if the bytes of the distinct objects
touched since the object's last access, and its own, fit the capacity.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

SCHEMA = "worker int, step long, object_id long, object_bytes long, distance long"


def stream(epoch: DataFrame, sizes: DataFrame, key: str = "bundle_id", workers: int = 1) -> DataFrame:
    """Accesses of an epoch (step, sample_id, bundle_id): objects are bundles, or samples where nothing is shared."""
    rows = epoch.join(sizes.select("bundle_id", "object_bytes"), "bundle_id")
    return rows.select(F.pmod("step", F.lit(workers)).cast("int").alias("worker"), "step", F.col(key).alias("object_id"), "object_bytes")


def repeated(accesses: DataFrame, epochs: int) -> DataFrame:
    """Warm epochs: the same ids again, with the cache kept; steps go on."""
    last = accesses.agg(F.max("step")).first()[0] or 0
    return accesses.withColumn("e", F.explode(F.sequence(F.lit(0), F.lit(epochs - 1)))).withColumn("step", F.col("step") + F.col("e") * (last + 1)).drop("e")


def paged(accesses: DataFrame, page: int = 4096) -> DataFrame:
    """The granularity of a page cache: sizes in whole pages."""
    return accesses.withColumn("object_bytes", F.ceil(F.col("object_bytes") / page).cast("long") * page)


def distances_by_join(accesses: DataFrame) -> DataFrame:
    """By definition: a self join on ranges of steps. Quadratic; reference for small streams."""
    prev = accesses.withColumn("prev", F.lag("step").over(Window.partitionBy("worker", "object_id").orderBy("step")))
    a, b = prev.alias("a"), prev.alias("b")
    since = (F.col("a.worker") == F.col("b.worker")) & (F.col("b.step") > F.col("a.prev")) & (F.col("b.step") < F.col("a.step")) & (F.coalesce(F.col("b.prev"), F.lit(-1)) <= F.col("a.prev"))
    sums = a.join(b, since).groupBy(F.col("a.worker").alias("worker"), F.col("a.step").alias("step")).agg(F.sum("b.object_bytes").alias("d"))
    out = prev.join(sums, ["worker", "step"], "left")
    return out.select("worker", "step", "object_id", "object_bytes", F.when(F.col("prev").isNotNull(), F.coalesce("d", F.lit(0))).alias("distance"))


def distances(accesses: DataFrame) -> DataFrame:
    """One pass over each worker's stream with a Fenwick tree of the bytes at each object's last step: n log n, state bounded by the
    worker's objects. A first access has no distance. Workers are the unit of parallelism; deal long epochs over many."""

    def run(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("step").to_numpy(), kind="stable")
        table = table.take(pa.array(order))
        size, n = table.column("object_bytes").to_numpy(), table.num_rows
        _, ids = np.unique(table.column("object_id").to_numpy(), return_inverse=True)
        tree, last, out = [0] * (n + 1), {}, []

        def add(i, v):
            i += 1
            while i <= n:
                tree[i] += v
                i += i & -i

        def upto(i):
            s = 0
            while i > 0:
                s += tree[i]
                i -= i & -i
            return s

        for i, (o, b) in enumerate(zip(ids.tolist(), size.tolist())):
            at = last.get(o)
            if at is None:
                out.append(None)
            else:
                out.append(upto(i) - upto(at + 1))
                add(at, -b)
            add(i, b)
            last[o] = i
        return table.select(["worker", "step", "object_id", "object_bytes"]).append_column("distance", pa.array(out, pa.int64()))

    return accesses.select(F.col("worker").cast("int").alias("worker"), F.col("step").cast("long").alias("step"), "object_id", F.col("object_bytes").cast("long").alias("object_bytes")).groupBy("worker").applyInArrow(run, SCHEMA)


def sampled(accesses: DataFrame, rate: int) -> DataFrame:
    """Spatial sampling for long streams: one of ``rate`` objects by hash; distances of the sample times the rate estimate those of all."""
    return accesses.where(F.pmod(F.xxhash64("object_id"), F.lit(rate)) == 0)


def sweep(found: DataFrame, body_bytes: int, shares: tuple[int, ...] = tuple(range(10, 101, 10))) -> DataFrame:
    """Hits and missed bytes at each capacity, a percentage of the body, from one pass over the distances."""
    caps = F.explode(F.array(*[F.struct(F.lit(s).alias("share"), F.lit(body_bytes * s // 100).cast("long").alias("capacity")) for s in shares]))
    hit = F.col("distance").isNotNull() & (F.col("distance") + F.col("object_bytes") <= F.col("c.capacity"))
    return found.withColumn("c", caps).groupBy(F.col("c.share").alias("share"), F.col("c.capacity").alias("capacity")).agg(F.count("*").alias("accesses"), F.sum(hit.cast("long")).alias("hits"), F.sum(F.when(~hit, F.col("object_bytes")).otherwise(0)).alias("miss_bytes"))


def lru(accesses: DataFrame, capacity: int) -> DataFrame:
    """The cache itself, one for each worker: an ordered map in one pass. worker, hits, miss_bytes."""

    def run(table: pa.Table) -> pa.Table:
        from collections import OrderedDict

        order = np.argsort(table.column("step").to_numpy(), kind="stable")
        held, used, hits, missed = OrderedDict(), 0, 0, 0
        for o, b in zip(table.column("object_id").to_numpy()[order].tolist(), table.column("object_bytes").to_numpy()[order].tolist()):
            if o in held:
                hits += 1
                held.move_to_end(o)
                continue
            missed += b
            held[o] = b
            used += b
            while used > capacity and held:
                used -= held.popitem(last=False)[1]
        return pa.table({"worker": pa.array([table.column("worker")[0].as_py()], pa.int32()), "hits": [hits], "miss_bytes": [missed]})

    return accesses.select(F.col("worker").cast("int").alias("worker"), "step", "object_id", "object_bytes").groupBy("worker").applyInArrow(run, "worker int, hits long, miss_bytes long")


def closed_form(share: float, n_pairs: int, n_bundles: int) -> float:
    """Expected hit rate for equal bundles: the capacity's share times one less the inverse ratio."""
    return share * (1 - n_bundles / n_pairs) if n_pairs else 0.0
