"""Media columns: content-addressed payloads in tar shards.

A payload of bytes is stored without loss as an 8-bit greyscale PNG of fixed width; the digest of the stored form is its address and
its member name. Each distinct content is stored once: the row with the least doc_id of equal texts writes it. Rows carry digest,
shard, offset and length; metadata columns come from a range read of the image header alone, features from a range read of the member.

Shards are ordinary tar files in the shared folder, written through ``pyarrow.fs``, so any store that it knows will do. A task writes
its shards under names of its own attempt and the index of members is a written table: a task that runs again leaves unread files
behind at worst, and the index never points to a part of one.

Null texts count as empty; an empty payload is one row of padding. Repeated rows and equal texts share one member and equal values.
An empty table gives an empty table. A text of any length is one member.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairbundle.llm.common import doc_text, documents, shared_path, staged, text_key, with_group_facts

#: Fixed values of the PNG format: signature and the byte positions of its header.
PNG_SIGNATURE = b"\x89PNG\r\n\x1a\n"
HEADER_BYTES = 33


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def to_png(payload: bytes, width: int) -> bytes:
    """The payload as rows of an 8-bit greyscale image."""
    rows = np.frombuffer(payload, np.uint8).reshape(-1, width)
    lines = np.zeros((len(rows), width + 1), np.uint8)
    lines[:, 1:] = rows
    head = struct.pack(">IIBBBBB", width, len(rows), 8, 0, 0, 0, 0)
    return PNG_SIGNATURE + _chunk(b"IHDR", head) + _chunk(b"IDAT", zlib.compress(lines.tobytes(), 1)) + _chunk(b"IEND", b"")


def png_size(head: bytes) -> tuple[int, int, int]:
    """Width, height and bits of a sample from the first bytes of an image."""
    if head[:8] != PNG_SIGNATURE or head[12:16] != b"IHDR":
        raise ValueError("not an image of this format")
    return struct.unpack(">IIB", head[16:25])


def from_png(data: bytes) -> np.ndarray:
    """The samples of an image written by ``to_png``, or by any writer of the same kind without filters."""
    width, height, bits = png_size(data[:HEADER_BYTES])
    at, body = 8, []
    while at < len(data):
        n, kind = struct.unpack(">I4s", data[at : at + 8])
        if kind == b"IDAT":
            body.append(data[at + 8 : at + 8 + n])
        at += 12 + n
    lines = np.frombuffer(zlib.decompress(b"".join(body)), np.uint8).reshape(height, width + 1)
    if bits != 8 or lines[:, 0].any():
        raise ValueError("filters or other depths are not used here")
    return lines[:, 1:]


def tar_header(name: str, size: int) -> bytes:
    """A ustar header for a plain file."""
    head = struct.pack("100s8s8s8s12s12s8sc100s6s2s32s32s8s8s155s12x", name.encode(), b"0000644\0", b"0000000\0", b"0000000\0", b"%011o\0" % size, b"00000000000\0", b" " * 8, b"0", b"", b"ustar\0", b"00", b"", b"", b"", b"", b"")
    return head[:148] + b"%06o\0 " % sum(head) + head[156:]


def average_hash(samples: np.ndarray) -> str:
    """Feature: which of 64 even stretches of the samples lie above the mean, as hexadecimal digits, and the mean in hundredths."""
    flat = samples.ravel()
    means = np.add.reduceat(flat, np.arange(64) * (len(flat) // 64), dtype=np.int64) / np.diff(np.append(np.arange(64) * (len(flat) // 64), len(flat)))
    return f"{int.from_bytes(np.packbits(means > flat.mean()).tobytes(), 'big'):016x}:{int(round(float(flat.mean()) * 100))}"


def _store(root: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(root)


def write_members(payloads: DataFrame, root: str, width: int, shard_bytes: int = 256 << 20) -> DataFrame:
    """Stores each row's payload; the index: key, n_bytes, digest, shard, offset, length.

    ``payloads`` has key and text, a row for each distinct content."""

    def run(batches):
        filesystem, base = _store(root)
        out, size, name = None, 0, ""
        try:
            for batch in batches:
                keys, texts = (c.to_pylist() for c in batch.columns)
                index: tuple = ([], [], [], [], [], [])
                for key, text in zip(keys, texts):
                    payload = text + b"\xff" * ((-len(text)) % width or (0 if text else width))
                    media = to_png(payload, width)
                    digest = hashlib.sha256(media).hexdigest()
                    if out is None or size + len(media) > shard_bytes:
                        if out is not None:
                            out.write(b"\0" * 1024)
                            out.close()
                        name, size = f"{uuid.uuid4().hex}.tar", 0
                        out = filesystem.open_output_stream(f"{base}/{name}")
                    out.write(tar_header(f"{digest}.png", len(media)))
                    out.write(media)
                    out.write(b"\0" * ((-len(media)) % 512))
                    for column, value in zip(index, (key, len(text), digest, name, size + 512, len(media))):
                        column.append(value)
                    size += 512 + len(media) + (-len(media)) % 512
                kinds = (pa.binary(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(index, kinds)], ["key", "n_bytes", "digest", "shard", "offset", "length"])
        finally:
            if out is not None:
                out.write(b"\0" * 1024)
                out.close()

    filesystem, base = _store(root)
    filesystem.create_dir(base, recursive=True)
    return payloads.select("key", "text").mapInArrow(run, "key binary, n_bytes long, digest string, shard string, offset long, length long")


def header_columns(index: DataFrame, root: str) -> DataFrame:
    """Adds width, height and bits: range reads of the image headers, none of the samples."""

    def run(batches):
        filesystem, base = _store(root)
        for b in batches:
            found, held, name = [], None, None
            for shard, offset in zip(b.column("shard").to_pylist(), b.column("offset").to_pylist()):
                if shard != name:
                    held, name = filesystem.open_input_file(f"{base}/{shard}"), shard
                found.append(png_size(held.read_at(HEADER_BYTES, offset)))
            yield pa.RecordBatch.from_arrays([*b.columns, *(pa.array([f[k] for f in found], pa.int32()) for k in range(3))], [*b.schema.names, "width", "height", "bits"])

    fields = ", ".join(f"{n} {t}" for n, t in index.dtypes)
    return index.mapInArrow(run, f"{fields}, width int, height int, bits int")


def features(index: DataFrame, root: str) -> DataFrame:
    """Reads the stored bytes of every member back and adds what they give."""
    added = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"

    def run(batches):
        filesystem, base = _store(root)
        for b in batches:
            rows: tuple = ([], [], [], [], [], [])
            held, name = None, None
            for shard, offset, length, digest in zip(*(b.column(c).to_pylist() for c in ("shard", "offset", "length", "digest"))):
                if shard != name:
                    held, name = filesystem.open_input_file(f"{base}/{shard}"), shard
                media = held.read_at(length, offset)
                if (found := hashlib.sha256(media).hexdigest()) != digest:
                    raise ValueError(f"a member of {shard} differs from its address")
                samples = from_png(media)
                payload = samples.tobytes()
                values = (len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(media), found, average_hash(samples))
                for column, value in zip(rows, values):
                    column.append(value)
            kinds = (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string())
            yield pa.RecordBatch.from_arrays([*b.columns, *(pa.array(c, t) for c, t in zip(rows, kinds))], [*b.schema.names, *(x.split()[0] for x in added.split(", "))])

    fields = ", ".join(f"{n} {t}" for n, t in index.dtypes)
    return index.mapInArrow(run, f"{fields}, {added}")


def media_columns(docs: DataFrame, width: int = 576, most_broadcast: int = 1_000_000) -> DataFrame:
    """Every row with its member's address, header columns and features. Up to ``most_broadcast`` copies (40 bytes each) are sent to the
    tasks that read texts, so that no payload is shuffled; more are joined."""
    rows = doc_text(docs)
    root = shared_path(docs.sparkSession, "media")
    doc = F.coalesce("doc_id", F.lit(-(2**63))).alias("doc")
    keyed = staged(rows.select("doc_id", doc, text_key().alias("key")), "media-rows", narrow=False)
    first = staged(keyed.groupBy("key").agg(F.min("doc").alias("first"), F.count("*").alias("rows")), "media-keys", narrow=True)
    pairs = with_group_facts(keyed.select("doc", "key"), first, ["key"], "rows")
    others = staged(pairs.where("doc <> first").select("doc", "key").distinct(), "media-copies", narrow=True)
    texts = rows.select(doc, text_key().alias("key"), F.col("text").cast("binary").alias("text"))
    if others.count() <= most_broadcast:  # payloads stay where they are read
        payloads = texts.join(F.broadcast(others), ["doc", "key"], "left_anti")
    else:
        payloads = texts.join(others, ["doc", "key"], "left_anti")
    index = staged(write_members(payloads, root, width), "media-index")
    # Rows of equal doc_id and text may write twice. The sizes of groups join here, where rows are dealt by key and still narrow.
    index = index.dropDuplicates(["key"]).join(first.select("key", "rows"), "key")
    known = features(header_columns(index.repartition("shard").sortWithinPartitions("shard", "offset"), root), root)
    known = staged(known, "media-known", narrow=True)
    return with_group_facts(keyed, known, ["key"], "rows").drop("doc", "key", "rows")


def op6_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_columns(documents(spark, sf_dir)).select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "width", "height", "digest")
