"""Token-id output: Re-Pair grammar compression of shards of documents.

A shard holds consecutive documents in doc_id order. Each round counts adjacent id pairs exactly, gives the most frequent ones a
nonterminal each and replaces their non-overlapping occurrences, until no pair is frequent; pairs never reach across a document's end. A shard's blob stores the
rules, how many ids each nonterminal expands to, the start of every document and the remaining symbols, so that one document, or
one position in it, is decoded without the rest. Blobs are rows of a Parquet table in the shared folder: a lost task writes its rows
again under Spark's commit protocol, and any store that Spark reaches will do.

Nulls: a null text is an empty one, which yields the end id alone. Equal doc_ids keep all their rows, ordered by text. An empty table
yields an empty table. Texts of any length are encoded whole; a shard closes after ``shard_tokens`` ids or the document that passes it.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairbundle.llm.common import doc_text, documents, shared_path
from pairbundle.llm.tokens import encoder, text_batches, tokenizer_path
from pairbundle.operators.addressing import prefix_sum

#: Fixed values of the file format: magic, version, and the header's fields (version, first nonterminal, documents, ids, rules, symbols).
MAGIC = b"RPGS"
VERSION = 1
HEADER = "<4sIIQQQQ"

#: Symbols are stored in 24 bits, so there are no more rules than these leave room for.
SYMBOLS = 1 << 24

#: At most 2 ** SLOT_BITS slots of a hash hold the pairs of a round.
SLOT_BITS = 18


def count_pairs(left: np.ndarray, right: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Exact counts of the pairs that occur ``least`` times: which occurrences were looked at, the group of each, and the count and pair
    of each group. An occurrence is left out only where its whole hash slot holds fewer than ``least``.

    In each slot one pair is counted by the slot's number; whatever else falls there is told apart by sorting."""
    bits = min(SLOT_BITS, max(8, len(left).bit_length()))
    slot = left * np.uint32(0x9E3779B1)
    slot ^= right * np.uint32(0x85EBCA77)
    slot >>= np.uint32(32 - bits)
    at = np.flatnonzero((np.bincount(slot, minlength=1 << bits) >= least)[slot])
    group, keys = slot[at].astype(np.int64), (left[at].astype(np.uint64) << np.uint64(32)) | right[at]
    stands = np.zeros(1 << bits, np.uint64)
    stands[group] = keys
    other = np.flatnonzero(stands[group] != keys)
    more, back = np.unique(keys[other], return_inverse=True)
    group[other] = (1 << bits) + back
    return at, group, np.bincount(group, minlength=len(stands) + len(more)), np.concatenate([stands, more])


def repair(ids: np.ndarray, last: np.ndarray, first_symbol: int, rounds: int | None = None, per_round: int = 8192, min_count: int = 6):
    """Replaces pairs by nonterminals until none within a document occurs ``min_count`` times. ``last`` marks each document's final id.

    A round replaces the ``per_round`` most frequent pairs (and those as frequent as the last of them); ``rounds`` bounds the rounds if
    given. All occurrences of a replaced pair vanish, so only pairs with a new symbol can gain: a round looks at these (``open_at``) and
    at frequent ones that earlier rounds left.

    Returns the remaining symbols, their ``last`` marks and the rules, an array of pairs; rule k is symbol ``first_symbol + k``."""
    seq, rules, total = ids.astype(np.uint32), [np.zeros((0, 2), np.uint32)], 0
    open_at = ~last
    while rounds is None or len(rules) <= rounds:
        at = np.flatnonzero(open_at)
        some, group, n, pairs = count_pairs(seq[at], seq[at + 1], min_count)
        at, frequent = at[some], n >= min_count
        floor = min_count if np.count_nonzero(frequent) <= per_round else int(np.partition(n, -per_round)[-per_round])
        chosen = np.flatnonzero(n >= floor)[: SYMBOLS - first_symbol - total]
        if not len(chosen):
            break
        symbol = np.zeros(len(n), np.uint32)
        symbol[chosen] = first_symbol + total + np.arange(len(chosen), dtype=np.uint32)
        to = symbol[group]
        open_at[:] = False
        open_at[at[frequent[group] & (to == 0)]] = True
        at, to = at[to > 0], to[to > 0]
        opens = np.diff(at, prepend=-2) != 1  # occurrences that overlap form runs: every other one stays
        run = at[np.maximum.accumulate(np.where(opens, np.arange(len(at)), 0))]
        stay = ((at - run) & 1) == 0
        at, to = at[stay], to[stay]
        seq[at] = to
        last[at] = last[at + 1]
        open_at[at] = True
        open_at[at[at > 0] - 1] = True
        keep = np.ones(len(seq), bool)
        keep[at + 1] = False
        seq, last, open_at = seq[keep], last[keep], open_at[keep]
        open_at &= ~last
        rules.append(np.stack([pairs[chosen] >> np.uint64(32), pairs[chosen] & np.uint64(0xFFFFFFFF)], 1).astype(np.uint32))
        total += len(chosen)
    return seq, last, np.concatenate(rules)


def expansion_lengths(rules: np.ndarray, first_symbol: int) -> np.ndarray:
    """How many ids each nonterminal stands for. Rules of a round refer to earlier rounds only, but lengths are resolved for any order."""
    size = np.zeros(len(rules), np.int64)
    todo = np.arange(len(rules))
    while len(todo):
        parts = []
        for side in (0, 1):
            s = rules[todo, side].astype(np.int64)
            parts.append(np.where(s < first_symbol, 1, size[np.maximum(s - first_symbol, 0)]))
        ready = (parts[0] > 0) & (parts[1] > 0)
        size[todo[ready]] = (parts[0] + parts[1])[ready]
        todo = todo[~ready]
    return size


def _pack24(a: np.ndarray) -> bytes:
    return np.ascontiguousarray(a.astype("<u4").view(np.uint8).reshape(-1, 4)[:, :3]).tobytes()


def _unpack24(data: bytes, n: int, at: int) -> np.ndarray:
    wide = np.zeros((n, 4), np.uint8)
    wide[:, :3] = np.frombuffer(data, np.uint8, 3 * n, at).reshape(n, 3)
    return wide.view("<u4").ravel()


def encode_shard(doc_ids: np.ndarray, ids: np.ndarray, lengths: np.ndarray, first_symbol: int, **options) -> bytes:
    """One shard: header; doc_ids; first symbol and id count of each document; rules; expansion lengths; symbols."""
    last = np.zeros(len(ids), bool)
    last[np.cumsum(lengths) - 1] = True
    seq, last, rules = repair(ids, last, first_symbol, **options)
    begins = np.concatenate([[0], np.flatnonzero(last) + 1]).astype("<i8")
    head = struct.pack(HEADER, MAGIC, VERSION, first_symbol, len(doc_ids), len(ids), len(rules), len(seq))
    return b"".join([head, doc_ids.astype("<i8").tobytes(), begins.tobytes(), lengths.astype("<i8").tobytes(), _pack24(rules.ravel()), expansion_lengths(rules, first_symbol).astype("<u4").tobytes(), _pack24(seq)])


class Shard:
    """Random access to an encoded shard."""

    def __init__(self, blob: bytes):
        magic, version, self.first_symbol, n, self.n_ids, rules, symbols = struct.unpack_from(HEADER, blob)
        if magic != MAGIC or version != VERSION:
            raise ValueError("not a grammar shard")
        at = struct.calcsize(HEADER)
        self.doc_ids = np.frombuffer(blob, "<i8", n, at)
        self.begins = np.frombuffer(blob, "<i8", n + 1, at := at + 8 * n)
        self.lengths = np.frombuffer(blob, "<i8", n, at := at + 8 * (n + 1))
        self.rules = _unpack24(blob, 2 * rules, at := at + 8 * n).reshape(-1, 2)
        self.sizes = np.frombuffer(blob, "<u4", rules, at := at + 6 * rules).astype(np.int64)
        self.symbols = _unpack24(blob, symbols, at + 4 * rules)
        self._expand()

    def _expand(self) -> None:
        """The ids of every nonterminal, one after another; rules refer to earlier ones."""
        plain = np.arange(self.first_symbol)
        self.size_of = np.concatenate([np.ones(self.first_symbol, np.int64), self.sizes])
        self.starts = self.first_symbol + np.cumsum(self.sizes) - self.sizes
        self.start_of = np.concatenate([plain, self.starts])
        self.flat = np.concatenate([plain, np.zeros(int(self.sizes.sum()), np.int64)]).astype(np.uint32)
        done = np.zeros(len(self.rules), bool)
        side = self.rules.astype(np.int64) - self.first_symbol
        while not done.all():
            now = np.flatnonzero(~done & ((side[:, 0] < 0) | done[np.maximum(side[:, 0], 0)]) & ((side[:, 1] < 0) | done[np.maximum(side[:, 1], 0)]))
            left = np.where(side[now, 0] < 0, 1, self.sizes[np.maximum(side[now, 0], 0)])
            for k, to in ((0, self.starts[now]), (1, self.starts[now] + left)):
                self._put(self.rules[now, k], to)
            done[now] = True

    def _put(self, symbols: np.ndarray, to: np.ndarray) -> None:
        ids, n = self._ids(symbols)
        self.flat[np.repeat(to - (np.cumsum(n) - n), n) + np.arange(len(ids))] = ids

    def _ids(self, symbols: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All symbols expanded: plain ids stand for themselves at the head of the table of expansions."""
        n = self.size_of[symbols]
        ends = np.cumsum(n)
        return self.flat[np.repeat(self.start_of[symbols] - (ends - n), n) + np.arange(int(ends[-1]) if len(ends) else 0)], n

    def document(self, k: int) -> np.ndarray:
        return self._ids(self.symbols[self.begins[k] : self.begins[k + 1]])[0]

    def token(self, k: int, position: int) -> int:
        """One id of a document: the expansion lengths lead to its symbol, then its rules downwards."""
        symbols = self.symbols[self.begins[k] : self.begins[k + 1]].astype(np.int64)
        n = np.where(symbols < self.first_symbol, 1, self.sizes[np.maximum(symbols - self.first_symbol, 0)] if len(self.sizes) else 1)
        ends = np.cumsum(n)
        j = int(np.searchsorted(ends, position, side="right"))
        symbol, position = int(symbols[j]), position - int(ends[j] - n[j])
        while symbol >= self.first_symbol:
            left, right = map(int, self.rules[symbol - self.first_symbol])
            size = 1 if left < self.first_symbol else int(self.sizes[left - self.first_symbol])
            symbol, position = (left, position) if position < size else (right, position - size)
        return symbol

    def all_ids(self) -> np.ndarray:
        return self._ids(self.symbols)[0]


def write_shards(docs: DataFrame, path: str, vocabulary: str | None = None, end_id: int = 0, first_symbol: int = 1 << 16, shard_tokens: int = 1_500_000, **options) -> None:
    """Encodes all documents and writes the shards, in ascending doc_id order, to ``path``.

    ``first_symbol`` is above every id of the vocabulary and above ``end_id``."""
    vocabulary = vocabulary or tokenizer_path("byte_bpe_50k.json")

    def encode(batches):
        held: list = []
        size, part = 0, 0

        def close():
            doc_ids, ids, lengths = (np.concatenate(x) for x in zip(*held))
            return pa.RecordBatch.from_arrays([pa.array([int(doc_ids[0])]), pa.array([part]), pa.array([len(doc_ids)]), pa.array([len(ids)]), pa.array([encode_shard(doc_ids, ids, lengths, first_symbol, **options)], pa.binary())], ["first_doc", "part", "n_docs", "n_ids", "blob"])

        for batch in batches:
            doc_ids, texts = batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_pylist()
            for a, b in text_batches(texts):
                ids, n = encoder(vocabulary).encode(texts[a:b])
                ends = np.cumsum(n)
                ids = np.insert(ids, ends, end_id) if len(ends) else ids
                held.append((doc_ids[a:b], ids, n + 1))
                size += len(ids)
                if size >= shard_tokens:
                    yield close()
                    held, size, part = [], 0, part + 1
        if held:
            yield close()

    rows = docs.select(F.coalesce("doc_id", F.lit(-(2**63))).alias("doc_id"), "text")
    rows.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text").mapInArrow(encode, "first_doc long, part long, n_docs long, n_ids long, blob binary").write.parquet(path)


def read_shards(spark: SparkSession, path: str) -> DataFrame:
    """Every document from its shard: doc_id, start, n_tokens, ids_crc32. Where shards start comes from their small columns alone."""
    shards = spark.read.parquet(path)
    starts = prefix_sum(shards.select("first_doc", "part", "n_ids"), ["first_doc", "part", "n_ids"], {"base": "n_ids"})

    def decode(batches):
        for batch in batches:
            for first, part, n_ids, blob in zip(*(c.to_pylist() for c in batch.columns)):
                shard = Shard(blob)
                data = shard.all_ids().astype("<u4").tobytes()
                ends = np.cumsum(shard.lengths)
                crc = [zlib.crc32(data[4 * (e - n) : 4 * e]) for e, n in zip(ends.tolist(), shard.lengths.tolist())]
                k = len(crc)
                yield pa.RecordBatch.from_arrays([pa.array([first] * k, pa.int64()), pa.array([part] * k, pa.int64()), pa.array([n_ids] * k, pa.int64()), pa.array(shard.doc_ids), pa.array(ends - shard.lengths), pa.array(shard.lengths), pa.array(crc, pa.int64())], ["first_doc", "part", "n_ids", "doc_id", "within", "n_tokens", "ids_crc32"])

    found = shards.select("first_doc", "part", "n_ids", "blob").mapInArrow(decode, "first_doc long, part long, n_ids long, doc_id long, within long, n_tokens long, ids_crc32 long")
    return found.join(starts, ["first_doc", "part", "n_ids"]).select(F.expr("nullif(doc_id, -9223372036854775808)").alias("doc_id"), (F.col("base") + F.col("within")).alias("start"), "n_tokens", "ids_crc32")


def op2_grammar_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = shared_path(spark, "grammar-shards")
    write_shards(doc_text(documents(spark, sf_dir)), path)
    return read_shards(spark, path)
