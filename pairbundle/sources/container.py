"""The packed container: a Spark data source ``pairbundle`` with a binary encoding of its own.

A shard file holds a header block (magic, version, JSON), encoded bundles one after another (length and bytes of the media, number of
texts, then length and bytes of each), the index of its own bundles as Parquet, and a trailer that says where the index begins. Writer
tasks write whole shards under names of their attempt; the commit on the driver writes header.json, with one line for each shard, which
alone makes them part of the container, so tasks may run twice. Readers plan shards and shares of shards from those lines; tasks read
the index of their shard. Filters on bundle_id or sample ranges drop shards in the plan and bundles in the tasks, before any body is
read. Rows move as Arrow batches. Paths are whatever ``pyarrow.fs`` opens.
"""

from __future__ import annotations

import json
import struct
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, InputPartition, WriterCommitMessage
from pyspark.sql.datasource import EqualTo, GreaterThan, GreaterThanOrEqual, In, LessThan, LessThanOrEqual
from dataclasses import dataclass

#: Fixed values of the file format.
MAGIC = b"PBDL"
VERSION = 2
HEAD = "<4sIQ"
TAIL = "<QQ4s"

#: Columns of a shard's index.
INDEX = ("bundle_id", "start_idx", "end_idx", "byte_offset", "byte_len")

#: Bodies are read, and rows handed on, in runs of at most so many bytes (or one bundle).
RUN_BYTES = 8 << 20

SCHEMA = "bundle_id long, start_idx long, end_idx long, media binary, texts array<string>"


def encode_bundle(media: bytes, texts: list[bytes]) -> bytes:
    """The bytes of one bundle; their number is 8 + media + 4 for each text + its bytes."""
    parts = [struct.pack("<I", len(media)), media, struct.pack("<I", len(texts))]
    for t in texts:
        parts += [struct.pack("<I", len(t)), t]
    return b"".join(parts)


def decode_bundle(data: bytes, at: int = 0) -> tuple[bytes, list[bytes], int]:
    """Media, texts and the position after the bundle."""
    (n,) = struct.unpack_from("<I", data, at)
    media, at = bytes(data[at + 4 : at + 4 + n]), at + 4 + n
    (k,) = struct.unpack_from("<I", data, at)
    at += 4
    texts = []
    for _ in range(k):
        (n,) = struct.unpack_from("<I", data, at)
        texts.append(bytes(data[at + 4 : at + 4 + n]))
        at += 4 + n
    return media, texts, at


def header_block(fields: dict) -> bytes:
    body = json.dumps(fields, sort_keys=True).encode()
    return struct.pack(HEAD, MAGIC, VERSION, len(body)) + body


def parse_header(data: bytes) -> tuple[dict, int]:
    magic, version, n = struct.unpack_from(HEAD, data)
    if magic != MAGIC or version != VERSION:
        raise ValueError("not a bundle container")
    at = struct.calcsize(HEAD)
    return json.loads(data[at : at + n]), at + n


def header(kind: str, n_pairs: int, n_bundles: int, ratio: int | None = None) -> dict:
    """The fields that a kind of pairing needs; ranges and offsets are the index."""
    out = {"kind": kind, "n_pairs": n_pairs, "n_bundles": n_bundles}
    return out | {"ratio": ratio} if kind == "fixed" else out


def filesystem(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path if "://" in path else f"file://{path}")


def _head_json(path: str) -> dict:
    store, base = filesystem(path)
    with store.open_input_file(f"{base}/header.json") as f:
        return json.loads(f.read())


def read_header(path: str) -> dict:
    """kind and counts, without any shard."""
    return {k: v for k, v in _head_json(path).items() if k != "shards"}


def read_shards(path: str) -> list[dict]:
    """One entry for each shard: its name, bundles, texts, bytes, and the least and greatest value of each indexed column."""
    return _head_json(path)["shards"]


def read_index(store, file: str) -> pa.Table:
    """The index at the end of a shard: two range reads."""
    import pyarrow.parquet as pq

    with store.open_input_file(file) as f:
        size, tail = f.size(), struct.calcsize(TAIL)
        at, n, magic = struct.unpack(TAIL, f.read_at(tail, size - tail))
        if magic != MAGIC:
            raise ValueError("a shard without its index")
        return pq.read_table(pa.BufferReader(f.read_at(n, at)))


@dataclass
class Written(WriterCommitMessage):
    shard: dict | None


@dataclass
class Share(InputPartition):
    """Part ``number`` of ``parts`` equal parts, by bundles, of a shard."""

    shard: str
    number: int
    parts: int


class BundleWriter(DataSourceArrowWriter):
    def __init__(self, path: str):
        self.path = path

    def write(self, iterator: Iterator[pa.RecordBatch]) -> WriterCommitMessage:
        import pyarrow.parquet as pq

        store, base = filesystem(self.path)
        name, at, n_texts, out, sizes, kept = f"{uuid.uuid4().hex}.bundles", 0, 0, None, [], []
        for batch in iterator:
            if not batch.num_rows:
                continue
            if out is None:
                store.create_dir(base, recursive=True)
                out = store.open_output_stream(f"{base}/{name}")
                head = header_block({"shard": name})
                out.write(head)
                at = len(head)
            media = batch.column("media").cast(pa.binary())
            texts = batch.column("texts").cast(pa.list_(pa.binary()))
            for m, t in zip(media, texts):
                data = encode_bundle(m.as_py(), held := t.as_py() or [])
                out.write(data)
                sizes.append(len(data))
                n_texts += len(held)
            kept.append(batch.select(INDEX[:3]))
        if out is None:
            return Written(None)
        lengths = np.array(sizes, np.int64)
        index = pa.Table.from_batches(kept).append_column("byte_offset", pa.array(at + np.cumsum(lengths) - lengths)).append_column("byte_len", pa.array(lengths))
        block = pa.BufferOutputStream()
        pq.write_table(index, block)
        data = block.getvalue()
        out.write(data)
        out.write(struct.pack(TAIL, at + int(lengths.sum()), len(data), MAGIC))
        out.close()
        ranges = {c: [int(index.column(c).to_numpy().min()), int(index.column(c).to_numpy().max())] for c in INDEX[:3]}
        owned = index.column("end_idx").to_numpy() - index.column("start_idx").to_numpy() + 1
        return Written({"shard": name, "n_bundles": index.num_rows, "n_pairs": int(owned.sum()), "n_texts": n_texts, "least": int(owned.min()), "most": int(owned.max()), "bytes": int(lengths.sum()), "ranges": ranges})

    def commit(self, messages) -> None:
        store, base = filesystem(self.path)
        store.create_dir(base, recursive=True)
        shards = sorted((m.shard for m in messages if m is not None and m.shard), key=lambda s: s["ranges"]["bundle_id"])
        least, most = min((s["least"] for s in shards), default=0), max((s["most"] for s in shards), default=0)
        total = lambda name: sum(s[name] for s in shards)
        kind = "uni_modal" if not total("n_texts") else "one_to_one" if least == most == 1 else "fixed" if least == most else "hybrid"
        with store.open_output_stream(f"{base}/header.json") as f:
            f.write(json.dumps(header(kind, total("n_pairs"), total("n_bundles"), least) | {"shards": shards}).encode())

    def abort(self, messages) -> None:
        store, base = filesystem(self.path)
        for m in messages:
            if m is not None and m.shard:
                store.delete_file(f"{base}/{m.shard['shard']}")


#: How a filter reads a column's least and greatest value, and the column itself.
WITHIN = {
    "eq": lambda lo, hi, v: lo <= v <= hi,
    "gt": lambda lo, hi, v: hi > v,
    "ge": lambda lo, hi, v: hi >= v,
    "lt": lambda lo, hi, v: lo < v,
    "le": lambda lo, hi, v: lo <= v,
    "in": lambda lo, hi, v: any(lo <= x <= hi for x in v),
}


class BundleReader(DataSourceReader):
    def __init__(self, path: str, stretch_bytes: int):
        self.path, self.stretch_bytes = path, stretch_bytes
        self.tests: list[tuple[str, str, object]] = []

    def partitions(self):
        out = []
        for s in read_shards(self.path):
            if all(WITHIN[sign](*s["ranges"][name], value) for name, sign, value in self.tests):
                parts = max(1, min(s["n_bundles"], -(-s["bytes"] // self.stretch_bytes)))
                out += [Share(s["shard"], k, parts) for k in range(parts)]
        return out or [Share("", 0, 1)]

    def read(self, partition):
        import pyarrow.compute as pc

        if not partition.shard:
            return
        store, base = filesystem(self.path)
        file = f"{base}/{partition.shard}"
        index = read_index(store, file)
        first, last = (index.num_rows * k // partition.parts for k in (partition.number, partition.number + 1))
        index = index.slice(first, last - first)
        how = {"eq": pc.equal, "gt": pc.greater, "ge": pc.greater_equal, "lt": pc.less, "le": pc.less_equal}
        for name, sign, value in self.tests:
            column = index.column(name)
            index = index.filter(pc.is_in(column, pa.array(list(value), pa.int64())) if sign == "in" else how[sign](column, value))
        at, size = (index.column(c).to_numpy().tolist() for c in ("byte_offset", "byte_len"))
        with store.open_input_file(file) as f:
            low = 0
            while low < len(at):
                high = low + 1
                while high < len(at) and at[high] == at[high - 1] + size[high - 1] and at[high] + size[high] - at[low] <= RUN_BYTES:
                    high += 1
                data = f.read_at(at[high - 1] + size[high - 1] - at[low], at[low])
                held = [decode_bundle(data, at[k] - at[low])[:2] for k in range(low, high)]
                ids = index.slice(low, high - low).select(INDEX[:3]).combine_chunks()
                media = pa.array([m for m, _ in held], pa.binary())
                texts = pa.array([t for _, t in held], pa.list_(pa.string()))
                yield pa.RecordBatch.from_arrays([*(ids.column(k).combine_chunks() for k in range(3)), media, texts], names=["bundle_id", "start_idx", "end_idx", "media", "texts"])
                low = high


def find_pair(path: str, sample_id: int) -> tuple[int, bytes, str | None, int] | None:
    """One pair without a job: bundle_id, media, text, and the comparisons that the balanced order of ranges took. The shard comes from
    the header, its index is halved down to the range that holds the id, and only that bundle is read."""
    store, base = filesystem(path)
    for s in read_shards(path):
        (low, _), (_, high) = s["ranges"]["start_idx"], s["ranges"]["end_idx"]
        if not low <= sample_id <= high:
            continue
        index = read_index(store, f"{base}/{s['shard']}")
        starts, ends = (index.column(c).to_numpy() for c in ("start_idx", "end_idx"))
        rows = np.flatnonzero(ends >= starts)
        lo, hi, compared = 0, len(rows), 0
        while lo < hi:
            mid = (lo + hi) // 2
            k, compared = int(rows[mid]), compared + 1
            if starts[k] <= sample_id <= ends[k]:
                with store.open_input_file(f"{base}/{s['shard']}") as f:
                    media, texts, _ = decode_bundle(f.read_at(index.column("byte_len")[k].as_py(), index.column("byte_offset")[k].as_py()))
                place = sample_id - int(starts[k])
                return index.column("bundle_id")[k].as_py(), media, texts[place].decode() if texts else None, compared
            lo, hi = (lo, mid) if sample_id < starts[k] else (mid + 1, hi)
    return None


class PruningBundleReader(BundleReader):
    """Spark refuses readers with this method unless the session allows filters to be pushed to Python sources."""

    def pushFilters(self, filters):
        """bundle_id, start_idx and end_idx are known from the index; other filters stay with Spark."""
        signs = {EqualTo: "eq", GreaterThan: "gt", GreaterThanOrEqual: "ge", LessThan: "lt", LessThanOrEqual: "le", In: "in"}
        for f in filters:
            name = getattr(f, "attribute", ())
            if type(f) in signs and len(name) == 1 and name[0] in ("bundle_id", "start_idx", "end_idx"):
                self.tests.append((name[0], signs[type(f)], f.value))
            else:
                yield f


class BundleFileSource(DataSource):
    """``spark.dataSource.register(BundleFileSource)``, then format ``pairbundle``. Options: path; stretch_bytes of a read task; pushdown."""

    @classmethod
    def name(cls):
        return "pairbundle"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        kind = PruningBundleReader if self.options.get("pushdown", "true").lower() == "true" else BundleReader
        return kind(self.options["path"], int(self.options.get("stretch_bytes", 64 << 20)))

    def writer(self, schema, overwrite):
        return BundleWriter(self.options["path"])


def write_container(found, path: str, shards: int | None = None) -> None:
    """Whole bundles to a container; ``shards=1`` gives one file."""
    from pyspark.sql import functions as F

    found.sparkSession.dataSource.register(BundleFileSource)
    rows = found.select("bundle_id", "start_idx", "end_idx", F.col("media").cast("binary").alias("media"), F.transform("texts", lambda t: t["text"]).alias("texts"))
    rows = rows.coalesce(1).sortWithinPartitions("bundle_id") if shards == 1 else (rows.repartitionByRange(shards, "bundle_id") if shards else rows.repartitionByRange("bundle_id")).sortWithinPartitions("bundle_id")
    rows.write.format("pairbundle").mode("append").save(path)


def read_container(spark, path: str):
    """Rows of SCHEMA. Filters reach the index if ``spark.sql.python.filterPushdown.enabled`` is set, which is a session's own choice."""
    spark.dataSource.register(BundleFileSource)
    allowed = spark.conf.get("spark.sql.python.filterPushdown.enabled", "false")
    return spark.read.format("pairbundle").option("pushdown", allowed).load(path)


def index_table(spark, path: str):
    """shard and INDEX of every bundle, from the ends of the shards; offsets are places in the shard."""
    from pyspark.sql import functions as F

    names = [s["shard"] for s in read_shards(path)]
    shards = spark.createDataFrame([(n,) for n in names], "shard string").repartition(max(1, min(len(names), 4 * spark.sparkContext.defaultParallelism)))

    def load(batches):
        store, base = filesystem(path)
        for b in batches:
            for name in b.column(0).to_pylist():
                for part in read_index(store, f"{base}/{name}").to_batches():
                    yield pa.RecordBatch.from_arrays([pa.array([name] * part.num_rows, pa.string()), *part.columns], names=["shard", *INDEX])

    return shards.mapInArrow(load, "shard string, " + ", ".join(f"{c} long" for c in INDEX)).select("shard", *[F.col(c) for c in INDEX])


def load_pairs(requests, path: str, stretch_bytes: int = 64 << 20):
    """Pairs for a batch of requests (sample_id), each bundle read once: sample_id, bundle_id, media, text.

    Ids are found in the shards' indexes by the rule of the header; what is shuffled is ids and places, by stretches of the shards, and
    never media. Tasks read runs of neighbouring bundles."""
    from pyspark.sql import functions as F

    from pairbundle.operators.locate import locate

    spark = requests.sparkSession
    index = index_table(spark, path).withColumn("byte_offset", F.struct("shard", "byte_offset"))
    found = locate(requests.select("sample_id"), index, read_header(path)).select("sample_id", "bundle_id", "text_pos", "byte_offset.shard", "byte_offset.byte_offset", "byte_len")
    dealt = found.repartition("shard", F.floor(F.col("byte_offset") / stretch_bytes)).sortWithinPartitions("shard", "byte_offset", "sample_id")

    def fetch(batches):
        store, base = filesystem(path)
        name, file = None, None
        for b in batches:
            ids, bundle, place, shard, at, size = (c.to_pylist() for c in b.columns)
            low = 0
            while low < len(ids):
                high, wide = low + 1, size[low]
                while high < len(ids) and shard[high] == shard[low] and at[high] <= at[high - 1] + size[high - 1] and wide + size[high] <= RUN_BYTES:
                    wide += size[high]  # media go out once for each pair
                    high += 1
                if shard[low] != name:
                    name = shard[low]
                    file = store.open_input_file(f"{base}/{name}")
                data = file.read_at(at[high - 1] + size[high - 1] - at[low], at[low])
                media, texts, last = [], [], None
                for k in range(low, high):
                    if at[k] != last:
                        last, held = at[k], decode_bundle(data, at[k] - at[low])
                    media.append(held[0])
                    texts.append(held[1][place[k]] if held[1] else None)
                yield pa.RecordBatch.from_arrays([pa.array(ids[low:high], pa.int64()), pa.array(bundle[low:high], pa.int64()), pa.array(media, pa.binary()), pa.array(texts, pa.string())], names=["sample_id", "bundle_id", "media", "text"])
                low = high

    return dealt.mapInArrow(fetch, "sample_id long, bundle_id long, media binary, text string")


def validate(index):
    """Rows of the index (bundle_id, start_idx, end_idx, byte_offset, byte_len) that break order, contiguity or tiling: none."""
    from pyspark.sql import Window
    from pyspark.sql import functions as F

    part = index.withColumn("_p", F.floor(F.col("bundle_id") / 65536))
    w = Window.partitionBy("_p").orderBy("bundle_id")
    inner = part.withColumn("_b", F.lead("byte_offset").over(w)).withColumn("_s", F.lead("start_idx").over(w)).where("_b IS NOT NULL")
    edge = part.groupBy("_p").agg(F.min_by(F.struct("byte_offset", "start_idx"), "bundle_id").alias("first"), F.max_by(F.struct("bundle_id", "start_idx", "end_idx", "byte_offset", "byte_len"), "bundle_id").alias("last"))
    nxt = edge.select((F.col("_p") - 1).alias("_p"), F.col("first.byte_offset").alias("_b"), F.col("first.start_idx").alias("_s"))
    joints = edge.select("_p", "last").join(nxt, "_p").select("last.*", "_b", "_s")
    cols = ["bundle_id", "start_idx", "end_idx", "byte_offset", "byte_len"]
    both = inner.select(*cols, "_b", "_s").union(joints.select(*cols, "_b", "_s"))
    return both.where("byte_offset + byte_len <> _b OR byte_len <= 0 OR _s <> greatest(end_idx, start_idx - 1) + 1").select(*cols)


def size_ratio(clusters):
    """Media bytes over text bytes, and whether whole-unit reads are advisable: media should outweigh texts by ten."""
    from pyspark.sql import functions as F

    return clusters.agg((F.sum("media_bytes") / F.count("*")).alias("mean_media"), (F.sum("text_bytes") / F.sum("n_texts")).alias("mean_text")).withColumn("size_ratio", F.round(F.col("mean_media") / F.col("mean_text"), 6)).withColumn("media_dominant", F.col("size_ratio") > 10)
