"""The balanced range index: a node for each bundle that owns ids, ordered by its range."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairbundle.operators.addressing import dense_ids


def build(index: DataFrame, mode: str = "distributed") -> DataFrame:
    """Node table by median splits, without recursion on the driver: a node is known by the segment of ranks it splits.

    node_id is the rank of the bundle among those that own ids; a segment [lo, hi) has its node at (lo + hi) div 2."""
    owned = index.where("end_idx >= start_idx").select("bundle_id", "start_idx", "end_idx", "byte_offset")
    ranked = dense_ids(owned, ["start_idx"], "node_id", mode)
    m = ranked.count()
    levels = max(1, m.bit_length())
    start = F.struct(F.lit(0).cast("long").alias("lo"), F.lit(m).cast("long").alias("hi"), F.lit(0).alias("depth"), F.lit(False).alias("found"))

    def halve(s, _):
        mid = F.floor((s["lo"] + s["hi"]) / 2)
        here, left = mid == F.col("node_id"), F.col("node_id") < mid
        down = F.struct(F.when(left, s["lo"]).otherwise(mid + 1).cast("long").alias("lo"), F.when(left, mid).otherwise(s["hi"]).cast("long").alias("hi"), (s["depth"] + 1).alias("depth"), F.lit(False).alias("found"))
        stay = F.struct(s["lo"].alias("lo"), s["hi"].alias("hi"), s["depth"].alias("depth"), F.lit(True).alias("found"))
        return F.when(s["found"] | here, stay).otherwise(down)

    seg = ranked.withColumn("s", F.aggregate(F.sequence(F.lit(1), F.lit(levels)), start, halve))
    child = lambda lo, hi: F.when(lo < hi, F.floor((lo + hi) / 2).cast("long"))
    size = F.col("s.hi") - F.col("s.lo")
    height = F.floor(F.log2(size.cast("double")) + 1e-12).cast("int") + 1
    return seg.select("node_id", "bundle_id", child(F.col("s.lo"), F.col("node_id")).alias("left_id"), child(F.col("node_id") + 1, F.col("s.hi")).alias("right_id"), height.alias("height"), (F.col("s.depth") + 1).cast("int").alias("depth"), "start_idx", "end_idx", "byte_offset")


def depth_stats(tree: DataFrame) -> DataFrame:
    """Nodes at each depth, from one."""
    return tree.groupBy("depth").agg(F.count("*").alias("nodes"))


def lookup_trace(tree: DataFrame, requests: DataFrame) -> DataFrame:
    """sample_id, bundle_id, comparisons: each id walks down the node table, one join for each level. For measuring, not for lookups."""
    root = tree.where("depth = 1").select("node_id").first()
    nodes = tree.select(F.col("node_id").alias("at"), "bundle_id", "left_id", "right_id", "start_idx", "end_idx")
    now = requests.select("sample_id").withColumn("at", F.lit(root[0] if root else None).cast("long")).withColumn("comparisons", F.lit(0))
    deepest = (tree.agg(F.max("depth")).first()[0] or 0) if root else 0
    out = None
    for _ in range(deepest):
        met = now.join(nodes, "at").withColumn("comparisons", F.col("comparisons") + 1)
        here = F.col("sample_id").between(F.col("start_idx"), F.col("end_idx"))
        hit = met.where(here).select("sample_id", "bundle_id", "comparisons")
        out = hit if out is None else out.union(hit)
        now = met.where(~here).select("sample_id", F.when(F.col("sample_id") < F.col("start_idx"), F.col("left_id")).otherwise(F.col("right_id")).alias("at"), "comparisons").where("at IS NOT NULL")
    return out if out is not None else now.select("sample_id", F.lit(None).cast("long").alias("bundle_id"), "comparisons").limit(0)


@dataclass
class Node:
    """A node of the driver-side tree for appends."""

    start: int
    end: int
    offset: int
    left: Node | None = None
    right: Node | None = None
    height: int = 1


def _height(n: Node | None) -> int:
    return n.height if n else 0


def _update(n: Node) -> Node:
    n.height = 1 + max(_height(n.left), _height(n.right))
    return n


def _turn(n: Node, side: str, other: str) -> Node:
    """The child on ``side`` becomes the parent."""
    up = getattr(n, side)
    setattr(n, side, getattr(up, other))
    setattr(up, other, _update(n))
    return _update(up)


def insert(root: Node | None, start: int, end: int, offset: int) -> Node:
    """Adds a range that overlaps none; at most two turns for each level restore the balance."""
    if root is None:
        return Node(start, end, offset)
    if end < root.start:
        root.left = insert(root.left, start, end, offset)
    elif start > root.end:
        root.right = insert(root.right, start, end, offset)
    else:
        raise ValueError(f"range {start}..{end} overlaps {root.start}..{root.end}")
    _update(root)
    lean = _height(root.left) - _height(root.right)
    if abs(lean) < 2:
        return root
    side, other = ("left", "right") if lean > 0 else ("right", "left")
    child = getattr(root, side)
    if _height(getattr(child, other)) > _height(getattr(child, side)):
        setattr(root, side, _turn(child, other, side))
    return _turn(root, side, other)


def find(root: Node | None, sample_id: int) -> tuple[int, int] | None:
    """Offset of the bundle and position in it."""
    while root is not None:
        if root.start <= sample_id <= root.end:
            return root.offset, sample_id - root.start
        root = root.left if sample_id < root.start else root.right
    return None


def check(root: Node | None) -> int:
    """The number of nodes; raises if order, balance or heights are broken."""
    count, last = 0, None

    def walk(n: Node | None) -> int:
        nonlocal count, last
        if n is None:
            return 0
        a = walk(n.left)
        if last is not None and n.start <= last:
            raise AssertionError("ranges out of order")
        last, count = n.end, count + 1
        b = walk(n.right)
        if abs(a - b) > 1 or n.height != 1 + max(a, b):
            raise AssertionError("out of balance")
        return n.height

    walk(root)
    return count
